"""URL filter: a blocked Bloom filter of listed canonical URLs passes possible hits to an exact hash join.

Lists of single pages hold canonical urls. The filter, 256 bits a block, discards nearly all urls that are not listed; the exact
join removes its false positives. Rules by host and start of a path stand above the list: a url's keys are its host and every parent
domain, each with every start of its path whose length occurs in the rules, so whatever rule fits the url is one of its keys, and the
longest decides.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Workspace, ascii_lower
from .warc import canonical_url

#: Eight odd multipliers, one for each 32-bit word of a block; the set bit of a word is the top five bits of the product.
SALTS = (0x47B6137B, 0x44974D91, 0x8824AD5B, 0xA2B7289D, 0x705495C7, 0x2DF1424B, 0x9EFC4947, 0x5C6BFB31)
#: Most rules that are literals, and most rows of a side that is broadcast; beyond it joins shuffle.
FEW_RULES, BROADCAST_ROWS = 64, 1_000_000


def url_host(url: Column) -> Column:
    """What follows the first :// up to a slash, question mark, hash or the end, A-Z lower-cased; empty if there is none."""
    return ascii_lower(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")))


def url_path(url: Column) -> Column:
    """What follows the host up to a question mark, hash or the end; empty if there is no ://."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def _block(key: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int")


def _masks(key: Column) -> list[Column]:
    low = F.xxhash64(key, F.lit(1)).bitwiseAND(F.lit(0xFFFFFFFF))
    return [F.call_function("shiftleft", F.lit(1).cast("bigint"), F.shiftright((F.shiftright(low, 1) * F.lit(s)).bitwiseAND(F.lit(0xFFFFFFFF)), 27).cast("int")) for s in SALTS]


def bloom_blocks(keys: DataFrame, n_keys: int, bits_per_key: int = 16) -> tuple[DataFrame, int]:
    """The filter as a table of 256-bit blocks, eight words each, and the number of blocks. keys: one string column, key."""
    blocks = max(1, -(-n_keys * bits_per_key // 256))
    words = [F.bit_or(m).alias(f"w{i}") for i, m in enumerate(_masks(F.col("key")))]
    return keys.groupBy(_block(F.col("key"), blocks).alias("block")).agg(*words), blocks


def _rules(rules: DataFrame) -> DataFrame:
    """key, rule, n (letters of the path), verdict of each distinct rule; block wins over allow where one is repeated."""
    ok = rules.where("host is not null and path is not null and host <> ''").select(ascii_lower(F.col("host")).alias("host"), "path", F.col("verdict").cast("string").alias("verdict"))
    one = ok.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))
    return one.select(F.concat_ws("\n", "host", "path").alias("key"), F.concat("host", "path").alias("rule"), F.length("path").alias("n"), "verdict")


def _keys(host: Column, path: Column, lengths: list[int]) -> Column:
    """Of each parent domain of a host and each start of a path of one of the lengths: one key."""
    labels = F.split(host, r"\.")
    parents = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels) - i + 1), "."))
    starts = [F.when(F.length(path) >= k, F.substring(path, 1, k)) for k in lengths]
    starts = F.filter(F.array(*starts), lambda x: x.isNotNull()) if starts else F.array().cast("array<string>")
    return F.when(host != "", F.flatten(F.transform(parents, lambda h: F.transform(starts, lambda p: F.concat_ws("\n", h, p)))))


def _by_rules(rows: DataFrame, rules: DataFrame) -> DataFrame:
    """rows with rule and rule_verdict of the longest rule that fits, or nulls."""
    best = F.struct(F.length("rule").alias("size"), F.col("rule"), F.col("verdict"))
    known = _rules(rules)
    sizes = known.groupBy("n").count().collect()  # one row for each length of a path, not for each rule
    lengths, total = sorted(r.n for r in sizes), sum(r["count"] for r in sizes)
    keys = _keys(F.col("host"), F.col("path"), lengths)
    if total <= FEW_RULES:
        entries = [F.struct(F.lit(r.key).alias("key"), F.lit(len(r.rule)).alias("size"), F.lit(r.rule).alias("rule"), F.lit(r.verdict).cast("string").alias("verdict")) for r in known.collect()]
        if not entries:
            return rows.withColumn("rule", F.lit(None).cast("string")).withColumn("rule_verdict", F.lit(None).cast("string"))
        fits = F.filter(F.array(*entries), lambda e: F.array_contains(F.col("__keys"), e["key"]))
        found = rows.withColumn("__keys", F.coalesce(keys, F.array().cast("array<string>"))).withColumn("__best", F.array_max(F.transform(fits, lambda e: F.struct(e["size"].alias("size"), e["rule"].alias("rule"), e["verdict"].alias("verdict")))))
    else:
        distinct = rows.where("host <> ''").select("host", "path").distinct().withColumn("key", F.explode(keys))
        listed = known.withColumn("best", best).select("key", "best")
        hits = distinct.join(F.broadcast(listed) if total <= BROADCAST_ROWS else listed, "key").groupBy("host", "path").agg(F.max("best").alias("__best"))
        found = rows.join(hits, ["host", "path"], "left")
    return found.select(*rows.columns, F.col("__best.rule").alias("rule"), F.col("__best.verdict").alias("rule_verdict"))


def _by_list(rows: DataFrame, listed: DataFrame, url_col: str) -> DataFrame:
    """rows (with canonical) and whether the list holds their canonical url: filter first, exact join of what passes."""
    work = Workspace(rows.sparkSession, "url-filter")
    known = work.save(listed.select(canonical_url(F.col(url_col)).alias("key")).where("key is not null").distinct(), "listed")
    n = known.count()
    blocks, n_blocks = bloom_blocks(known, n)
    held = F.col("w0").isNotNull()
    for i, m in enumerate(_masks(F.coalesce("canonical", F.lit("")))):
        held = held & (F.col(f"w{i}").bitwiseAND(m) == m)
    at = F.when(F.col("canonical").isNotNull(), _block(F.col("canonical"), n_blocks))
    tried = rows.withColumn("block", at).join(F.broadcast(blocks) if n_blocks <= BROADCAST_ROWS else blocks, "block", "left").withColumn("__held", held)
    # urls that the filter stops get keys of their own, so that a shuffle spreads them
    apart = F.concat(F.lit("\x01"), F.hex(F.xxhash64("canonical", F.monotonically_increasing_id())))
    tried = tried.withColumn("__key", F.when(F.col("__held"), F.col("canonical")).otherwise(apart))
    known = known.select(F.col("key").alias("__key"), F.lit(True).alias("__listed"))
    out = tried.join(F.broadcast(known) if n <= BROADCAST_ROWS else known, "__key", "left")
    return out.select(*rows.columns, (F.col("__held") & F.coalesce("__listed", F.lit(False))).alias("listed"))


def judge_urls(
    pages: DataFrame, rules: DataFrame, listed: DataFrame | None = None, id_col: str = "page_id", url_col: str = "url", default: str = "allow"
) -> DataFrame:
    """Judges every url by the longest rule that fits it, else blocks what is listed, else by default.

    Gives id, host, path, rule, verdict, listed. rules: host, path, verdict; a rule fits its host and all subdomains, if the url's
    path starts with its path. listed: a column of urls (named as url_col), which block every url of the same canonical form (see
    warc.canonical_url). Null urls and urls without :// have an empty host and path, fit no rule and are never listed. Repeated rows
    and equal ids each give a row of their own; empty tables give no rows; with no rules and no list every url gets the default. Of a
    rule that is repeated, block wins over allow. Null hosts, paths and urls in rules or list are ignored, as are other columns.

    Only ids and urls are read. Up to FEW_RULES rules are literals, up to BROADCAST_ROWS rules, blocks of the filter and listed urls
    are broadcast, and then nothing is shuffled but the list; beyond, joins shuffle, and hot keys are split by Spark's adaptive skew
    join.
    """
    url = F.col(url_col)
    rows = pages.select(F.col(id_col).alias("page_id"), url_host(url).alias("host"), url_path(url).alias("path"), canonical_url(url).alias("canonical"))
    judged = _by_rules(rows, rules)
    judged = _by_list(judged, listed, url_col) if listed is not None else judged.withColumn("listed", F.lit(False))
    verdict = F.coalesce("rule_verdict", F.when(F.col("listed"), F.lit("block")), F.lit(default))
    return judged.select(F.col("page_id").alias(id_col), "host", "path", "rule", verdict.alias("verdict"), "listed")
