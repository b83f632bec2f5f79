"""Licence scans by sentence rules: normalised sentences become identifiers, identifier sequences match ordered licence rules."""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Sentences of published notices and licence texts, normalised as normal_sentence() does, with their identifiers.
NOTICES = [
    # Apache License 2.0, the notice for source files
    ("you may not use this file except in compliance with the license", "ApacheComply"),
    ("you may obtain a copy of the license at", "ApacheCopy"),
    ("you may obtain a copy of the license at http www apache org licenses license 2 0", "ApacheCopyAt"),
    ("you may obtain a copy of the license at https www apache org licenses license 2 0", "ApacheCopyAt"),
    ("http www apache org licenses license 2 0", "ApacheUrl"),
    ("https www apache org licenses license 2 0", "ApacheUrl"),
    (
        "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis"
        " without warranties or conditions of any kind either express or implied",
        "ApacheUnless",
    ),
    ("see the license for the specific language governing permissions and limitations under the license", "ApacheSee"),
    # MIT
    ("permission is hereby granted free of charge to any person obtaining a copy of this software", "MitGrant"),
    (
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"
        " to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute"
        " sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the"
        " following conditions",
        "MitGrant",
    ),
    ("the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "MitNotice"),
    ("the software is provided as is without warranty of any kind", "AsIs"),
    (
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of"
        " merchantability fitness for a particular purpose and noninfringement",
        "AsIs",
    ),
    (
        "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of"
        " contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
        "MitLiability",
    ),
    # BSD
    ("redistribution and use in source and binary forms with or without modification are permitted", "BsdGrant"),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "BsdGrant"),
    ("redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", "BsdSource"),
    (
        "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in"
        " the documentation and or other materials provided with the distribution",
        "BsdBinary",
    ),
    (
        "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not"
        " limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
        "BsdAsIs",
    ),
    (
        "in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or"
        " consequential damages including but not limited to procurement of substitute goods or services",
        "BsdLiability",
    ),
    (
        "in no event shall the copyright owner or contributors be liable for any direct indirect incidental special exemplary or"
        " consequential damages including but not limited to procurement of substitute goods or services",
        "BsdLiability",
    ),
    ("loss of use data or profits", "BsdLoss"),
    (
        "or business interruption however caused and on any theory of liability whether in contract strict liability or tort including"
        " negligence or otherwise arising in any way out of the use of this software even if advised of the possibility of such damage",
        "BsdTheory",
    ),
    # ISC
    (
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that"
        " the above copyright notice and this permission notice appear in all copies",
        "IscGrant",
    ),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "ZeroBsdGrant"),
    (
        "the software is provided as is and the author disclaims all warranties with regard to this software including all implied"
        " warranties of merchantability and fitness",
        "IscAsIs",
    ),
    (
        "in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever"
        " resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of"
        " or in connection with the use or performance of this software",
        "IscLiability",
    ),
    # zlib
    ("this software is provided as is without any express or implied warranty", "ZlibAsIs"),
    ("in no event will the authors be held liable for any damages arising from the use of this software", "ZlibLiability"),
    (
        "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and"
        " redistribute it freely subject to the following restrictions",
        "ZlibGrant",
    ),
    # Mozilla, Eclipse, Boost, public domain, others
    ("this source code form is subject to the terms of the mozilla public license v", "MplSubject"),
    ("if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0", "MplCopy"),
    ("if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0", "MplCopy"),
    (
        "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0 which is"
        " available at https www eclipse org legal epl 2 0",
        "EplAvailable",
    ),
    (
        "this program and the accompanying materials are made available under the terms of the eclipse public license v1 0 which"
        " accompanies this distribution and is available at http www eclipse org legal epl v10 html",
        "Epl1Available",
    ),
    ("distributed under the boost software license version 1 0", "BoostRef"),
    ("this is free and unencumbered software released into the public domain", "Unlicense"),
    (
        "anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled"
        " binary for any purpose commercial or non commercial and by any means",
        "UnlicenseAnyone",
    ),
    ("all rights reserved", "AllRights"),
]
#: Holders that the third condition of the BSD licence names.
BSD_HOLDERS = [
    "copyright holder", "copyright holders", "copyright owner", "organization", "author", "project", "company", "university", "regents",
]
#: Names under which notices refer to a licence, and its identifier.
NAMES = [
    ("apache license version 2 0", "Apache-2.0"), ("apache license 2 0", "Apache-2.0"), ("apache 2 0 license", "Apache-2.0"),
    ("mit license", "MIT"), ("isc license", "ISC"), ("bsd license", "BSD"), ("bsd 2 clause license", "BSD-2-Clause"),
    ("2 clause bsd license", "BSD-2-Clause"), ("bsd 3 clause license", "BSD-3-Clause"), ("3 clause bsd license", "BSD-3-Clause"),
    ("zlib license", "Zlib"), ("unlicense", "Unlicense"), ("mozilla public license 2 0", "MPL-2.0"),
    ("mozilla public license version 2 0", "MPL-2.0"), ("eclipse public license 2 0", "EPL-2.0"),
    ("gnu general public license version 2", "GPL-2.0"), ("gnu general public license version 3", "GPL-3.0"),
    ("gnu general public license v2 0", "GPL-2.0"), ("gnu general public license v3 0", "GPL-3.0"), ("gplv2", "GPL-2.0"),
    ("gplv3", "GPL-3.0"), ("gnu gplv3", "GPL-3.0"), ("gpl v3", "GPL-3.0"), ("gnu lesser general public license version 3", "LGPL-3.0"),
    ("gnu lesser general public license version 2 1", "LGPL-2.1"), ("lgplv3", "LGPL-3.0"),
    ("gnu affero general public license version 3", "AGPL-3.0"), ("agplv3", "AGPL-3.0"),
    ("creative commons attribution 4 0 international license", "CC-BY-4.0"),
    ("creative commons attribution sharealike 4 0 international license", "CC-BY-SA-4.0"),
    ("creative commons attribution noncommercial 4 0 international license", "CC-BY-NC-4.0"),
    ("creative commons attribution noncommercial sharealike 4 0 international license", "CC-BY-NC-SA-4.0"),
]
#: What precedes and follows a licence's name in a notice of one sentence.
BEFORE = [
    "licensed under", "released under", "distributed under", "available under", "published under", "this work is licensed under",
    "this project is licensed under", "this software is licensed under", "this code is licensed under", "this program is licensed under",
    "this project is released under", "this software is released under", "this file is licensed under", "the code is licensed under",
]
AFTER = ["", "see the license file for details", "see license for details", "see the license md file for details", "see license file for details"]
#: Identifiers that stand alone in a line; versions of Creative Commons licences.
SPDX = [
    "Apache-2.0", "MIT", "ISC", "BSD-2-Clause", "BSD-3-Clause", "Zlib", "Unlicense", "MPL-2.0", "EPL-2.0", "BSL-1.0", "CC0-1.0", "0BSD",
    "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only",
    "LGPL-3.0-or-later", "AGPL-3.0-only", "AGPL-3.0-or-later", "Apache-2.0 OR MIT", "MIT OR Apache-2.0",
]
CC_VERSIONS, CC_KINDS = ["2.0", "2.5", "3.0", "4.0"], ["BY", "BY-SA", "BY-NC", "BY-NC-SA", "BY-ND", "BY-NC-ND"]
#: The GNU licences, their short names and versions.
GNU = [("gnu general public license", "GPL", ["2", "3"]), ("gnu lesser general public license", "LGPL", ["2.1", "3"]), ("gnu affero general public license", "AGPL", ["3"])]


def _plain(name: str) -> str:
    return " ".join("".join(c if c.isalnum() else " " for c in name.lower()).split())


def _gnu() -> tuple[list, list]:
    """Sentences and rules of the GNU notices; version 2 has semicolons where version 3 has one sentence."""
    sentences, rules = [], []
    for name, short, versions in GNU:
        for thing in ("program", "library", "software", "file"):
            sentences += [
                (f"this {thing} is free software", "GnuFree"),
                (f"this {thing} is free software you can redistribute it and or modify it under the terms of the {name}", f"{short}Free"),
                (f"this {thing} is distributed in the hope that it will be useful but without any warranty", "GnuHope"),
                (f"you should have received a copy of the {name} along with this {thing}", f"{short}Copy"),
            ]
        sentences += [
            (f"you can redistribute it and or modify it under the terms of the {name} as published by the free software foundation", f"{short}Terms"),
            (f"see the {name} for more details", f"{short}See"),
        ]
        for v in versions:
            sentences.append((f"either version {_plain(v)} of the license or at your option any later version", f"Either{v}"))
            for thing in ("program", "library", "software", "file"):
                sentences.append(
                    (
                        f"this {thing} is free software you can redistribute it and or modify it under the terms of the {name} as published by"
                        f" the free software foundation either version {_plain(v)} of the license or at your option any later version",
                        f"{short}{v}Later",
                    )
                )
            full = v if "." in v else f"{v}.0"
            tail = ("GnuHope", "GnuImplied", f"{short}See", f"{short}Copy")
            for head in ((f"{short}{v}Later",), ("GnuFree", f"{short}Terms", f"Either{v}")):
                rules += [((*head, *tail, "GnuIfNot"), f"{short}-{full}-or-later"), ((*head, *tail), f"{short}-{full}-or-later"), (head, f"{short}-{full}-or-later")]
            rules.append(((f"{short}Free", f"ref-{short}-{full}"), f"{short}-{full}"))
    sentences += [
        ("without even the implied warranty of merchantability or fitness for a particular purpose", "GnuImplied"),
        ("if not see http www gnu org licenses", "GnuIfNot"),
        ("if not see https www gnu org licenses", "GnuIfNot"),
    ]
    return sentences, rules


def _references() -> list[tuple[str, str]]:
    """Notices of one sentence: every name of a licence in every wording, and identifiers by themselves."""
    cc = [f"CC-{kind}-{v}" for kind in CC_KINDS for v in CC_VERSIONS]
    named = [*((f"the {n}", i) for n, i in NAMES), *((f"a {n}", i) for n, i in NAMES if n.startswith("creative")), *((n, i) for n, i in NAMES if not n.startswith("the")), *((_plain(i), i) for i in cc)]
    out = [(" ".join(x for x in (before, name, after) if x), f"ref-{i}") for before, (name, i), after in itertools.product(BEFORE, named, AFTER)]
    return out + [(f"spdx license identifier {_plain(i)}", f"ref-{i.replace(' ', '-')}") for i in [*SPDX, *cc]]


def _unique(rows: list) -> list:
    return list(dict(rows).items())


#: Known sentences and their identifiers: the first meaning of a sentence counts.
SENTENCES: list[tuple[str, str]] = _unique(reversed([*NOTICES, *((f"neither the name of the {h} nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", "BsdNames") for h in BSD_HOLDERS), *_gnu()[0], *_references()]))
_DISCLAIMER = ("BsdAsIs", "BsdLiability", "BsdLoss", "BsdTheory")
#: Rules in order, the longer ones first: identifiers that must follow each other and the licence they show. Matched ones are spent.
RULES: list[tuple[tuple[str, ...], str]] = [
    (("ref-Apache-2.0", "ApacheComply", "ApacheCopy", "ApacheUrl", "ApacheUnless", "ApacheSee"), "Apache-2.0"),
    (("ref-Apache-2.0", "ApacheComply", "ApacheCopyAt", "ApacheUnless", "ApacheSee"), "Apache-2.0"),
    (("ref-Apache-2.0", "ApacheComply", "ApacheCopy"), "Apache-2.0"),
    (("MitGrant", "MitNotice", "AsIs", "MitLiability"), "MIT"),
    (("BsdGrant", "BsdSource", "BsdBinary", "BsdNames", *_DISCLAIMER), "BSD-3-Clause"),
    (("BsdGrant", "BsdSource", "BsdBinary", *_DISCLAIMER), "BSD-2-Clause"),
    (("BsdGrant", "BsdSource", "BsdBinary", "BsdNames"), "BSD-3-Clause"),
    (("BsdGrant", "BsdSource", "BsdBinary"), "BSD-2-Clause"),
    (("IscGrant", "IscAsIs", "IscLiability"), "ISC"),
    (("ZeroBsdGrant", "IscAsIs", "IscLiability"), "0BSD"),
    (("ZlibAsIs", "ZlibLiability", "ZlibGrant"), "Zlib"),
    (("MplSubject", "MplCopy"), "MPL-2.0"),
    (("Unlicense", "UnlicenseAnyone"), "Unlicense"),
    *_gnu()[1],
    (("MitGrant", "AsIs"), "MIT"),
    (("BsdGrant", "AsIs"), "BSD"),
    *(((f"ref-{i}",), i) for i in dict.fromkeys([s[4:] for _, s in reversed(SENTENCES) if s.startswith("ref-")])),
    (("MitGrant",), "MIT"),
    (("IscGrant",), "ISC"),
    (("EplAvailable",), "EPL-2.0"),
    (("Epl1Available",), "EPL-1.0"),
    (("BoostRef",), "BSL-1.0"),
    (("Unlicense",), "Unlicense"),
    (("AllRights",), "Proprietary"),
]

#: What ends a sentence: stops before white space or the end, semicolons, and lines without letters or digits. A stop inside a version
#: number or an address ends none. What a notice defines in brackets, (the "License"), is no part of a sentence.
DEFINED, ENDS = r"\((the|this) [\"'“”A-Za-z ]{1,40}\)", r"[.!?]+[\"'”)]*([ \t\r\n]|$)|;|\n[^\p{L}\p{N}\n]*\n"


def sentences_of(text: Column) -> Column:
    """Sentences in order, each with its place: whole ones, whatever lines they are wrapped over, then their lines one by one."""
    marked = F.regexp_replace(F.regexp_replace(F.coalesce(text, F.lit("")), DEFINED, " "), ENDS, "\x01")

    def units(s, i):
        lines = F.split(s, "\n")
        return F.transform(F.when(F.size(lines) > 1, F.concat(F.array(s), lines)).otherwise(lines), lambda u, j: F.struct(i.alias("pos"), j.alias("line"), u.alias("raw")))

    return F.flatten(F.transform(F.split(marked, "\x01"), units))


def normal_sentence(sentence: Column) -> Column:
    """Lower case, every run of other characters than letters and digits one space, none at the ends."""
    return F.trim(F.regexp_replace(F.lower(sentence), r"[^\p{L}\p{N}]+", " "))


def match_rules(sequence: Column, rules=RULES) -> Column:
    """A struct of what is left of an identifier sequence (left) and the licences found, by the first rules first (found)."""
    whole = F.concat_ws("", F.transform(sequence, lambda s: F.concat(F.lit("<"), s, F.lit(">"))))
    steps = F.array(*[F.struct(F.lit("".join(f"<{i}>" for i in ids)).alias("run"), F.lit(licence).alias("licence")) for ids, licence in rules])
    start = F.struct(whole.alias("left"), F.array().cast("array<string>").alias("found"))

    def spend(now, rule):
        hit = F.contains(now["left"], rule["run"])
        return F.struct(F.replace(now["left"], rule["run"], F.lit("|")).alias("left"), F.when(hit, F.array_append(now["found"], rule["licence"])).otherwise(now["found"]).alias("found"))

    return F.aggregate(steps, start, spend)


def scan_licences(docs: DataFrame, sentences=SENTENCES, rules=RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, sentences, licences, unmatched of each document with a known sentence.

    sentences: the identifiers in the order of the text; licences: those of the rules that match, in the order of the rules;
    unmatched: identifiers no rule has used; each joined by spaces. A sentence counts whether it is wrapped over lines or a line by
    itself; sentences that are not known may stand between known ones. Null and empty texts have no sentence. Repeated rows give a
    row each, null ids are kept, an empty table gives none, other columns are ignored.

    Only array expressions and a hash join with the broadcast sentences (their number is the list's). What is shuffled are known
    sentences alone, by the row they come from, so no key is hot.
    """
    known = docs.sparkSession.createDataFrame(list(sentences), "sentence string, sid string")
    rows = docs.select(F.col(id_col).alias("doc_id"), sentences_of(F.col(text_col).cast("string")).alias("s")).withColumn("row", F.monotonically_increasing_id())
    one = rows.select("row", "doc_id", F.explode("s").alias("u")).select("row", "doc_id", "u.pos", "u.line", normal_sentence(F.col("u.raw")).alias("sentence"))
    hits = one.where("sentence <> ''").join(F.broadcast(known), "sentence")
    # of a sentence that is known as a whole its lines count no more
    whole = hits.groupBy("row", "doc_id", "pos").agg(F.min("line").alias("first"), F.collect_list(F.struct("pos", "line", "sid")).alias("l"))
    whole = whole.select("row", "doc_id", F.filter("l", lambda h: (h["line"] == 0) | (F.col("first") > 0)).alias("l"))
    ordered = whole.groupBy("row", "doc_id").agg(F.sort_array(F.flatten(F.collect_list("l"))).alias("hits"))
    sequence = ordered.select("doc_id", F.col("hits.sid").alias("ids")).withColumn("m", match_rules(F.col("ids"), rules))
    rest = F.trim(F.regexp_replace(F.replace("m.left", F.lit("|"), F.lit("")), "[<>]+", " "))
    return sequence.select("doc_id", F.array_join("ids", " ").alias("sentences"), F.array_join(F.array_distinct("m.found"), " ").alias("licences"), rest.alias("unmatched"))
