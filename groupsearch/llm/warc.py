"""WARC records: reading, writing, and resolving not-modified revisits.

A revisit with status 304 carries no body. It is joined, as of its time, to the latest earlier full response of the same canonical
url; if its validators agree with that response, the response's headers are taken with those of the revisit that a 304 may change.
"""

from __future__ import annotations

import gzip
import io
import zlib
from collections.abc import Iterator
from datetime import datetime, timezone

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ascii_lower, bounded_batches

#: Headers that a not-modified answer may carry and that replace the stored ones.
PERMITTED = ("cache-control", "content-location", "date", "etag", "expires", "vary")
#: Rows of one url that a time slice is made for; bytes of records that leave a reader at once.
SLICE_ROWS, READ_BYTES = 200_000, 16 << 20
RECORDS = "record_id string, kind string, url string, ts timestamp, status int, headers map<string,string>, body binary"


def canonical_url(url: Column) -> Column:
    """Host in lower case without a default port, path, and the sorted parameters except utm_ ones; no scheme, user or fragment.

    Null where the url is null or has no ://.
    """
    rest = F.regexp_extract(url, r"(?s)^[^:/?#]*://([^#]*)", 1)
    host = F.regexp_replace(ascii_lower(F.regexp_extract(rest, r"(?s)^(?:[^/?@]*@)?([^/?]*)", 1)), r":(80|443)$", "")
    path = F.regexp_extract(rest, r"(?s)^[^/?]*([^?]*)", 1)
    params = F.array_join(F.array_sort(F.filter(F.split(F.regexp_extract(rest, r"(?s)\?(.*)$", 1), "&"), lambda p: (p != "") & ~p.startswith("utm_"))), "&")
    whole = F.concat(host, F.when(path == "", F.lit("/")).otherwise(path), F.when(params != "", F.concat(F.lit("?"), params)).otherwise(F.lit("")))
    return F.when(url.rlike(r"^[^:/?#]*://"), whole)


class _Inflated(io.RawIOBase):
    """The members of a gzip file, one after the other, up to where it is cut off or damaged."""

    def __init__(self, raw: bytes):
        self.raw, self.at, self.member = memoryview(raw), 0, zlib.decompressobj(31)

    def readable(self) -> bool:
        return True

    def readinto(self, out) -> int:
        try:
            while self.at < len(self.raw):
                given = self.raw[self.at : self.at + (1 << 14)]
                got = self.member.decompress(given, len(out))
                self.at += len(given) - len(self.member.unused_data if self.member.eof else self.member.unconsumed_tail)
                if self.member.eof:
                    self.member = zlib.decompressobj(31)
                if got:
                    out[: len(got)] = got
                    return len(got)
        except zlib.error:
            pass
        return 0


def parse_warc(raw: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(record headers in lower case, block) of each record, one at a time; gzip members are inflated as they are reached.

    A cut-off or damaged end of the file is left out, records before it are not. A record whose length is missing, negative or no
    number is skipped; the next one is found by its first line.
    """
    f = io.BufferedReader(_Inflated(raw)) if raw[:2] == b"\x1f\x8b" else io.BytesIO(raw)
    while line := f.readline():
        if not line.startswith(b"WARC/"):
            continue
        head = _headers(f)
        size = head.get("content-length", "")
        if not (size.isascii() and size.isdigit()):
            continue
        block = f.read(int(size))
        if len(block) == int(size):
            yield head, block


def _headers(f) -> dict[str, str]:
    out = {}
    while (line := f.readline()).strip():
        k, _, v = line.decode("utf-8", "replace").partition(":")
        out[k.strip().lower()] = v.strip()
    return out


def write_warc(records: list[tuple[dict[str, str], bytes]], compress: bool = True) -> bytes:
    """A file of (headers, block) records, each its own gzip member."""
    out = []
    for head, block in records:
        lines = "".join(f"{k}: {v}\r\n" for k, v in head.items() if k.lower() != "content-length")
        raw = f"WARC/1.1\r\n{lines}Content-Length: {len(block)}\r\n\r\n".encode() + block + b"\r\n\r\n"
        out.append(gzip.compress(raw, mtime=0) if compress else raw)
    return b"".join(out)


def _record(head: dict[str, str], block: bytes) -> dict:
    f = io.BytesIO(block)
    first = f.readline().split()
    status = int(first[1]) if len(first) > 1 and first[1].isdigit() and len(first[1]) < 6 else None
    fields = _headers(f)
    try:
        ts = datetime.fromisoformat(head.get("warc-date", "").replace("Z", "+00:00"))
        ts = ts if ts.tzinfo else ts.replace(tzinfo=timezone.utc)
    except ValueError:
        ts = None
    return {"record_id": head.get("warc-record-id"), "kind": head["warc-type"], "url": head.get("warc-target-uri"), "ts": ts, "status": status, "headers": list(fields.items()), "body": f.read()}


def read_warc(spark, path: str) -> DataFrame:
    """Response and revisit records of WARC files, a file a task: see RECORDS. Files are read by Spark, so any store will do.

    A worker holds a file as it is stored, one inflated record and the rows of a batch of READ_BYTES.
    """
    bounded_batches(spark)

    def run(batches):
        for b in batches:
            for raw in b.column(0):
                rows, size = [], 0
                for head, block in parse_warc(raw.as_py()):
                    if head.get("warc-type") in ("response", "revisit"):
                        rows.append(_record(head, block))
                        size += len(block)
                    if size >= READ_BYTES:
                        yield pa.RecordBatch.from_pylist(rows, schema=_SCHEMA)
                        rows, size = [], 0
                yield pa.RecordBatch.from_pylist(rows, schema=_SCHEMA)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, RECORDS)


_SCHEMA = pa.schema(
    [("record_id", pa.string()), ("kind", pa.string()), ("url", pa.string()), ("ts", pa.timestamp("us", "UTC")), ("status", pa.int32()), ("headers", pa.map_(pa.string(), pa.string())), ("body", pa.binary())]
)


def _header_list(headers: Column) -> Column:
    return F.array_sort(F.transform(F.map_entries(F.coalesce(headers, F.create_map().cast("map<string,string>"))), lambda e: F.struct(F.lower(e["key"]).alias("k"), e["value"].alias("v"))))


def _field(entries: Column, name: str) -> Column:
    return F.get(F.filter(entries, lambda e: e["k"] == name), F.lit(0))["v"]


def resolve_revisits(records: DataFrame, slice_rows: int = SLICE_ROWS) -> DataFrame:
    """record_id, canonical, refers_to, outcome, headers of every revisit.

    records: record_id, kind (response or revisit), url, ts, status, headers. A full response has kind response and status 200.
    Outcome: resolved, validator_mismatch, no_validator (the revisit has neither ETag nor Last-Modified), no_earlier_response, or
    no_key (null url or time). The ETag decides where the revisit has one, else Last-Modified; weak and strong tags compare alike.
    headers: for resolved ones name: value lines sorted by name. A response at the very time of the revisit is not earlier; of
    responses at one time the largest record_id counts. Repeated rows give a row each; an empty table gives none; other columns,
    and bodies, are not read.

    Rows are partitioned by url and slice of time, cut at quantiles, so a url that a third of all records share spreads over the
    slices; the last response before a slice comes from one row for each url and slice.
    """
    fields = _header_list(F.col("headers"))
    rows = records.where("kind in ('response', 'revisit')").select(
        "record_id", (F.col("kind") == "revisit").alias("revisit"), canonical_url(F.col("url")).alias("key"), F.unix_micros("ts").alias("t"), "status", fields.alias("fields")
    )
    # without a url or time nothing can be earlier; those rows are spread by their id
    whole = rows.where("revisit or status = 200")
    sized = whole.agg(F.count("*").alias("n"), F.max("t").alias("t")).first()
    slices = max(1, -(-sized.n // slice_rows))
    if slices > 1:
        cuts = whole.agg(F.percentile_approx("t", [i / slices for i in range(1, slices)], 10_000)).first()[0] or []
        cuts = sorted(set(cuts))
        part = sum((F.when(F.col("t") > c, 1).otherwise(0) for c in cuts), F.lit(0)) if len(cuts) <= 64 else F.size(F.filter(F.lit(cuts), lambda c: c < F.col("t")))
    else:
        part = F.lit(0)
    full = F.when(~F.col("revisit"), F.struct("t", "record_id", "fields"))
    keyed = whole.where("key is not null and t is not null").withColumn("slice", part).withColumn("full", full)
    ends = keyed.where("not revisit").groupBy("key", "slice").agg(F.max("full").alias("end"))
    here = Window.partitionBy("key", "slice").orderBy("t").rangeBetween(Window.unboundedPreceding, -1)
    seen = keyed.withColumn("inside", F.max("full").over(here)).where("revisit")
    if slices > 1:
        ahead = Window.partitionBy("key").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
        marks = ends.unionByName(seen.select("key", "slice").distinct().withColumn("end", F.lit(None).cast(ends.schema["end"].dataType)))
        marks = marks.groupBy("key", "slice").agg(F.max("end").alias("end")).withColumn("before", F.max("end").over(ahead)).select("key", "slice", "before")
        seen = seen.join(marks, ["key", "slice"]).withColumn("prior", F.coalesce("inside", "before"))
    else:
        seen = seen.withColumn("prior", F.col("inside"))
    lone = whole.where("revisit and (key is null or t is null)").select("record_id", F.col("key"), "fields", F.lit(None).cast(ends.schema["end"].dataType).alias("prior"))
    both = seen.select("record_id", "key", "fields", "prior", F.lit(True).alias("keyed")).unionByName(lone.withColumn("keyed", F.lit(False)))

    def tag(c):
        return F.regexp_replace(c, "^W/", "")

    mine, theirs = F.col("fields"), F.col("prior.fields")
    agree = F.when(_field(mine, "etag").isNotNull(), F.coalesce(tag(_field(mine, "etag")) == tag(_field(theirs, "etag")), F.lit(False))).otherwise(
        F.coalesce(_field(mine, "last-modified") == _field(theirs, "last-modified"), F.lit(False))
    )
    outcome = (
        F.when(~F.col("keyed"), "no_key")
        .when(F.col("prior").isNull(), "no_earlier_response")
        .when(_field(mine, "etag").isNull() & _field(mine, "last-modified").isNull(), "no_validator")
        .when(agree, "resolved")
        .otherwise("validator_mismatch")
    )
    fresh = F.filter(mine, lambda e: e["k"].isin(*PERMITTED))
    names = F.transform(fresh, lambda e: e["k"])
    merged = F.array_sort(F.concat(F.filter(theirs, lambda e: ~F.array_contains(names, e["k"])), fresh))
    lines = F.array_join(F.transform(merged, lambda e: F.concat_ws(": ", e["k"], e["v"])), "\n")
    out = both.withColumn("outcome", outcome)
    ok = F.col("outcome") == "resolved"
    return out.select("record_id", F.col("key").alias("canonical"), F.when(F.col("prior").isNotNull(), F.col("prior.record_id")).alias("refers_to"), "outcome", F.when(ok, lines).alias("headers"))


def crawl_of_pages(pages: DataFrame) -> DataFrame:
    """Records of two visits to every page, as a crawler would have kept them: a response, then a revisit a year later.

    The response has the page's id as its second since 2024, its html's digest as ETag, and its time as Last-Modified; every eleventh
    failed (503). Revisits by id modulo 7: 1 sends another digest, 2 no validator, 3 its Last-Modified alone, 4 another one, 5 its
    digest as a weak tag, the others their digest. Pages that share a canonical url meet each other's records.
    """
    page = F.col("page_id")
    digest = F.concat(F.lit('"'), F.md5(F.coalesce("html", F.lit(""))), F.lit('"'))
    seconds, way = F.lit(1704067200) + page, F.pmod(page, F.lit(7))
    status = F.when(F.pmod(page, F.lit(11)) == 3, 503).otherwise(200)
    first = F.create_map(
        F.lit("Content-Type"), F.lit("text/html"), F.lit("ETag"), digest, F.lit("Last-Modified"), seconds.cast("string"), F.lit("Date"), seconds.cast("string"), F.lit("Cache-Control"), F.lit("max-age=60")
    )
    etag = F.when(way == 1, F.lit('"other"')).when(way == 5, F.concat(F.lit("W/"), digest)).when(~way.isin(2, 3, 4), digest)
    modified = F.when(way == 3, seconds.cast("string")).when(way == 4, F.lit("0"))
    again = F.create_map(F.lit("ETag"), etag, F.lit("Last-Modified"), modified, F.lit("Date"), (seconds + 31536000).cast("string"), F.lit("Server"), F.lit("cache"))
    kinds = F.array(
        F.struct(F.concat(F.lit("response-"), page).alias("record_id"), F.lit("response").alias("kind"), F.timestamp_seconds(seconds).alias("ts"), status.alias("status"), first.alias("headers")),
        F.struct(
            F.concat(F.lit("revisit-"), page).alias("record_id"),
            F.lit("revisit").alias("kind"),
            F.timestamp_seconds(seconds + 31536000).alias("ts"),
            F.lit(304).alias("status"),
            F.map_filter(again, lambda k, v: v.isNotNull()).alias("headers"),
        ),
    )
    return pages.select("url", F.explode(kinds).alias("r")).select("url", "r.*")
