"""License scans: ordered signature rules, keyword prefilter, interval-containment suppression.

DataFrame functions only, and no shuffle: each document is scanned where it is read. A few
words gate everything; a rule runs only on texts that hold its keyword once their blanks are collapsed,
as its pattern takes any blanks between words. Detections of rules
of lower order that lie inside a detection of the same or a higher order are suppressed.

Defined results: null and empty texts have no words, places or labels (score 0); rows repeated in
the input are repeated in the result; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import json
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import pick
from rpqframe.llm.spans import lower_ascii, matches

#: Base phrases and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}

#: Label, keyword, name pattern, SPDX identifier pattern, address pattern ("" where there is none).
FAMILIES = [
    ("gpl-3.0", "gpl|gnu general public", r"(?:gnu\s+general\s+public\s+licen[sc]e,?\s*(?:\(gpl\)\s*)?(?:as\s+published\s+by\s+the\s+free\s+software\s+foundation,?\s*(?:either\s+)?)?v(?:ersion)?\.?\s*3|gplv3|gpl[- ]3)", r"gpl-3\.0(?:-only|-or-later|\+)?", r"gnu\.org/licenses/gpl-3\.0"),
    ("gpl-2.0", "gpl|gnu general public", r"(?:gnu\s+general\s+public\s+licen[sc]e,?\s*v(?:ersion)?\.?\s*2|gplv2|gpl[- ]2)", r"gpl-2\.0(?:-only|-or-later|\+)?", r"gnu\.org/licenses/(?:old-licenses/)?gpl-2\.0"),
    ("gpl-any", "gpl|gnu general public", r"gnu\s+general\s+public\s+licen[sc]e", r"gpl-1\.0(?:-only|-or-later|\+)?", r"gnu\.org/(?:licenses|copyleft)/gpl"),
    ("lgpl-3.0", "lgpl|lesser general public", r"(?:gnu\s+lesser\s+general\s+public\s+licen[sc]e,?\s*v(?:ersion)?\.?\s*3|lgplv3|lgpl[- ]3)", r"lgpl-3\.0(?:-only|-or-later|\+)?", r"gnu\.org/licenses/lgpl-3\.0"),
    ("lgpl-2.1", "lgpl|lesser general public", r"(?:gnu\s+lesser\s+general\s+public\s+licen[sc]e,?\s*v(?:ersion)?\.?\s*2\.1|lgplv2\.1|lgpl[- ]2\.1)", r"lgpl-2\.1(?:-only|-or-later|\+)?", r"gnu\.org/licenses/(?:old-licenses/)?lgpl-2\.1"),
    ("lgpl-2.0", "lgpl|library general public", r"gnu\s+library\s+general\s+public\s+licen[sc]e", r"lgpl-2\.0(?:-only|-or-later|\+)?", ""),
    ("agpl-3.0", "agpl|affero", r"(?:gnu\s+affero\s+general\s+public\s+licen[sc]e|agplv3)", r"agpl-3\.0(?:-only|-or-later)?", r"gnu\.org/licenses/agpl"),
    ("gfdl", "free documentation", r"gnu\s+free\s+documentation\s+licen[sc]e", r"gfdl-1\.[123](?:-only|-or-later)?", r"gnu\.org/licenses/fdl"),
    ("apache-2.0", "apache", r"apache\s+(?:software\s+)?licen[sc]e,?\s*(?:version|v)?\.?\s*2(?:\.0)?", r"apache-2\.0", r"apache\.org/licenses/license-2\.0"),
    ("apache-1.1", "apache", r"apache\s+(?:software\s+)?licen[sc]e,?\s*(?:version|v)?\.?\s*1\.1", r"apache-1\.1", r"apache\.org/licenses/license-1\.1"),
    ("apache-1.0", "apache", r"apache\s+(?:software\s+)?licen[sc]e,?\s*(?:version|v)?\.?\s*1\.0", r"apache-1\.0", r"apache\.org/licenses/license-1\.0"),
    ("apache-any", "apache", r"apache\s+(?:software\s+)?licen[sc]e", "", r"apache\.org/licenses"),
    ("mit", "mit", r"(?:the\s+)?\bmit\s+licen[sc]e", r"mit", r"opensource\.org/licenses/mit"),
    ("mit-text", "permission is hereby granted", r"permission\s+is\s+hereby\s+granted,\s+free\s+of\s+charge,\s+to\s+any\s+person\s+obtaining\s+a\s+copy", r"mit-0", ""),
    ("x11", "x11", r"\bx11\s+licen[sc]e", r"x11", ""),
    ("isc", "isc", r"\bisc\s+licen[sc]e", r"isc", r"opensource\.org/licenses/isc"),
    ("bsd-4-clause", "bsd", r"(?:4[- ]clause\s+bsd|original\s+bsd|bsd\s+4[- ]clause)(?:\s+licen[sc]e)?", r"bsd-4-clause", ""),
    ("bsd-3-clause", "bsd", r"(?:3[- ]clause\s+bsd|(?:new|revised|modified)\s+bsd|bsd\s+3[- ]clause)(?:\s+licen[sc]e)?", r"bsd-3-clause", r"opensource\.org/licenses/bsd-3-clause"),
    ("bsd-2-clause", "bsd", r"(?:2[- ]clause\s+bsd|simplified\s+bsd|freebsd|bsd\s+2[- ]clause)\s+licen[sc]e", r"bsd-2-clause", r"opensource\.org/licenses/bsd-2-clause"),
    ("0bsd", "bsd", r"zero[- ]clause\s+bsd(?:\s+licen[sc]e)?", r"0bsd", ""),
    ("bsd-any", "bsd", r"\bbsd\s+licen[sc]e", r"bsd", ""),
    ("mpl-2.0", "mozilla|mpl", r"mozilla\s+public\s+licen[sc]e,?\s*(?:version|v)?\.?\s*2(?:\.0)?", r"mpl-2\.0", r"mozilla\.org/mpl/2\.0"),
    ("mpl-1.1", "mozilla|mpl", r"mozilla\s+public\s+licen[sc]e,?\s*(?:version|v)?\.?\s*1\.1", r"mpl-1\.1", r"mozilla\.org/mpl/mpl-1\.1"),
    ("mpl-any", "mozilla|mpl", r"mozilla\s+public\s+licen[sc]e", r"mpl-1\.0", r"mozilla\.org/mpl"),
    ("epl-2.0", "eclipse|epl", r"eclipse\s+public\s+licen[sc]e\s*-?,?\s*(?:version|v)?\.?\s*2(?:\.0)?", r"epl-2\.0", r"eclipse\.org/legal/epl-2\.0"),
    ("epl-1.0", "eclipse|epl", r"eclipse\s+public\s+licen[sc]e", r"epl-1\.0", r"eclipse\.org/legal/epl-v10"),
    ("cddl", "cddl|common development", r"common\s+development\s+and\s+distribution\s+licen[sc]e", r"cddl-1\.[01]", r"opensource\.org/licenses/cddl"),
    ("cpl", "common public", r"common\s+public\s+licen[sc]e", r"cpl-1\.0", ""),
    ("eupl", "european union public|eupl", r"european\s+union\s+public\s+licen[sc]e", r"eupl-1\.[012]", ""),
    ("cc-by-nc-sa", "cc by|cc-by|creative commons", r"(?:cc[- ]by[- ]nc[- ]sa|creative\s+commons\s+attribution[- ]noncommercial[- ]sharealike)(?:\s+[1-4]\.\d)?", r"cc-by-nc-sa-[1-4]\.\d", r"creativecommons\.org/licenses/by-nc-sa"),
    ("cc-by-nc-nd", "cc by|cc-by|creative commons", r"(?:cc[- ]by[- ]nc[- ]nd|creative\s+commons\s+attribution[- ]noncommercial[- ]noderiv\w*)(?:\s+[1-4]\.\d)?", r"cc-by-nc-nd-[1-4]\.\d", r"creativecommons\.org/licenses/by-nc-nd"),
    ("cc-by-nc", "cc by|cc-by|creative commons", r"(?:cc[- ]by[- ]nc|creative\s+commons\s+attribution[- ]noncommercial)(?:\s+[1-4]\.\d)?", r"cc-by-nc-[1-4]\.\d", r"creativecommons\.org/licenses/by-nc/"),
    ("cc-by-sa", "cc by|cc-by|creative commons", r"(?:cc[- ]by[- ]sa|creative\s+commons\s+attribution[- ]sharealike)(?:\s+[1-4]\.\d)?", r"cc-by-sa-[1-4]\.\d", r"creativecommons\.org/licenses/by-sa"),
    ("cc-by-nd", "cc by|cc-by|creative commons", r"(?:cc[- ]by[- ]nd|creative\s+commons\s+attribution[- ]noderiv\w*)(?:\s+[1-4]\.\d)?", r"cc-by-nd-[1-4]\.\d", r"creativecommons\.org/licenses/by-nd"),
    ("cc-by-4.0", "cc by|cc-by|creative commons", r"(?:cc[- ]by|creative\s+commons\s+attribution)\s+4\.0", r"cc-by-4\.0", r"creativecommons\.org/licenses/by/4"),
    ("cc-by-3.0", "cc by|cc-by|creative commons", r"(?:cc[- ]by|creative\s+commons\s+attribution)\s+3\.0", r"cc-by-3\.0", r"creativecommons\.org/licenses/by/3"),
    ("cc-by-any", "cc by|cc-by|creative commons", r"(?:cc[- ]by\b|creative\s+commons\s+attribution)", r"cc-by-[12]\.\d", r"creativecommons\.org/licenses/by/"),
    ("cc0", "cc0|publicdomain", r"\bcc0(?:\s+1\.0)?(?:\s+universal)?", r"cc0-1\.0", r"creativecommons\.org/publicdomain/zero"),
    ("cc-any", "creative commons", r"creative\s+commons\s+licen[sc]e", "", r"creativecommons\.org/licenses"),
    ("unlicense", "unlicense", r"\bthe\s+unlicense", r"unlicense", r"unlicense\.org"),
    ("public-domain", "public domain", r"(?:released|placed|dedicated)\s+(?:in)?to\s+the\s+public\s+domain", "", ""),
    ("wtfpl", "wtfpl", r"\bwtfpl", r"wtfpl", r"wtfpl\.net"),
    ("zlib", "zlib", r"\bzlib(?:/libpng)?\s+licen[sc]e", r"zlib", r"opensource\.org/licenses/zlib"),
    ("boost", "boost|bsl", r"boost\s+software\s+licen[sc]e", r"bsl-1\.0", r"boost\.org/license"),
    ("artistic", "artistic", r"artistic\s+licen[sc]e(?:\s+2\.0)?", r"artistic-[12]\.0", r"opensource\.org/licenses/artistic"),
    ("ofl", "open font|ofl", r"(?:sil\s+)?open\s+font\s+licen[sc]e", r"ofl-1\.[01]", r"scripts\.sil\.org/ofl"),
    ("psf", "python", r"python\s+software\s+foundation\s+licen[sc]e", r"(?:psf|python)-2\.0", ""),
    ("postgresql", "postgresql", r"postgresql\s+licen[sc]e", r"postgresql", ""),
    ("openssl", "openssl", r"openssl\s+licen[sc]e", r"openssl", ""),
    ("ncsa", "ncsa", r"(?:university\s+of\s+illinois/)?ncsa\s+open\s+source\s+licen[sc]e", r"ncsa", ""),
    ("ms-pl", "microsoft public|ms-pl", r"microsoft\s+public\s+licen[sc]e", r"ms-pl", ""),
    ("ms-rl", "microsoft reciprocal|ms-rl", r"microsoft\s+reciprocal\s+licen[sc]e", r"ms-rl", ""),
    ("odbl", "open database|odbl", r"open\s+database\s+licen[sc]e", r"odbl-1\.0", r"opendatacommons\.org/licenses/odbl"),
    ("osl-3.0", "open software licen|osl", r"open\s+software\s+licen[sc]e", r"osl-[123]\.\d", ""),
    ("afl-3.0", "academic free|afl", r"academic\s+free\s+licen[sc]e", r"afl-[123]\.\d", ""),
    ("proprietary", "all rights reserved|proprietary", r"(?:all\s+rights\s+reserved|proprietary\s+and\s+confidential)", r"licenseref-proprietary", ""),
    ("copyright", "copyright|©", r"(?:copyright|©)\s+(?:\(c\)\s*|©\s*)?(?:19|20)\d\d", "", ""),
]

#: Order, confidence and pattern of each way to state a license; N, S and U stand for name, identifier, address.
FORMS = [
    (0, 1.0, "S", r"spdx-license-identifier:\s*S\b"),
    (1, 0.95, "N", r"(?:licen[sc]ed|released|distributed|published|available|provided|covered|made\s+available)\s+under\s+(?:the\s+)?(?:terms\s+(?:and\s+conditions\s+)?of\s+)?(?:the\s+)?(?:an?\s+)?N"),
    (1, 0.95, "N", r"(?:governed\s+by|subject\s+to|under\s+the\s+terms\s+of)\s+(?:the\s+)?N"),
    (2, 0.9, "U", r"https?://(?:www\.)?U\S*"),
    (3, 0.8, "S", r"licen[sc]e\s*[:=]\s*[\"']?S\b"),
    (4, 0.7, "N", r"N"),
]


#: Label, rare keyword, and words of the license or of its notice itself; blanks stand for any blanks.
TEXTS = [
    ("gpl-notice", "free software", r"this program is free software:? you can redistribute it and/or modify"),
    ("gpl-text", "verbatim copies", r"everyone is permitted to copy and distribute verbatim copies of this license document"),
    ("lgpl-notice", "free software", r"this library is free software;? you can redistribute it and/or modify"),
    ("gpl-or-later", "any later version", r"either version [123] of the license,? or \(at your option\) any later version"),
    ("mit-text", "without restriction", r"to deal in the software without restriction, including without limitation the rights"),
    ("as-is", "without warranty", r"the software is provided .{0,3}as is.{0,3},? without warranty of any kind"),
    ("isc-text", "distribute this software", r"permission to use, copy, modify,? (?:and|and/or) distribute this software for any purpose"),
    ("bsd-text", "redistribution", r"redistribution and use in source and binary forms,? with or without modification,? are permitted"),
    ("bsd-3-text", "endorse or promote", r"may be used to endorse or promote products derived from this software without"),
    ("bsd-4-text", "advertising materials", r"all advertising materials mentioning features or use of this software must"),
    ("apache-2.0-notice", "except in compliance", r"you may not use this file except in compliance with the license"),
    ("mpl-2.0-notice", "source code form", r"this source code form is subject to the terms of the mozilla public license"),
    ("mpl-1.1-notice", "contents of this file", r"the contents of this file are subject to the mozilla public license"),
    ("epl-notice", "accompanying materials", r"this program and the accompanying materials are made available under the terms of the eclipse"),
    ("zlib-text", "express or implied", r"this software is provided .{0,3}as-is.{0,3},? without any express or implied warranty"),
    ("unlicense-text", "unencumbered", r"this is free and unencumbered software released into the public domain"),
    ("cc-notice", "creative commons", r"this work is (?:licensed|made available) under (?:a|the) creative commons"),
    ("artistic-text", "standard version", r"you may make and give away verbatim copies of the source form of the standard version"),
    ("boost-text", "machine-executable", r"machine-executable object code generated by a source language processor"),
    ("ofl-text", "font software", r"the font software may be modified, altered, or added to"),
]

#: Families whose names can be stated without the word licence; all other names need it.
FREE = set(
    "gpl-3.0 gpl-2.0 lgpl-3.0 lgpl-2.1 agpl-3.0 mit-text bsd-4-clause bsd-3-clause 0bsd cc-by-nc-sa cc-by-nc-nd cc-by-nc cc-by-sa cc-by-nd cc-by-4.0 cc-by-3.0 cc-by-any cc0 unlicense public-domain wtfpl proprietary copyright".split()
)


def rules() -> list[dict]:
    """All signature rules in their order: keywords (one of ``k`` and also ``k2`` must stand in the text), pattern, label, order, confidence."""
    out = [{"k": [key], "k2": "", "r": text.replace(" ", r"\s+"), "l": label, "o": 1, "c": 0.95} for label, key, text in TEXTS]
    for label, keywords, name, spdx, url in FAMILIES:
        for order, conf, part, form in FORMS:
            value = {"N": rf"(?<![a-z0-9])(?:{name})(?:s\b|(?![a-z0-9]))", "S": spdx, "U": url}[part]
            if value:
                own = keywords.split("|") if part == "N" else [{"S": "licen", "U": "http"}[part]]
                need = "licen" if part == "N" and label not in FREE else ""
                out.append({"k": own, "k2": need, "r": form.replace(part, value, 1) if part != "N" else form.removesuffix("N") + value, "l": label, "o": order, "c": conf})
    return sorted(out, key=lambda r: r["o"])


_RULE = "array<struct<k:array<string>,k2:string,r:string,l:string,o:int,c:double>>"
#: No rule can match a text without one of these.
_GATE = ["licen", "http", "gpl", "affero", "bsd", "cc by", "cc-by", "cc0", "commons", "domain", "wtfpl", "hereby", "reserved", "proprietary", "copyright", "©", "publicdomain", *sorted({k for _, k, _ in TEXTS})]


def detections(low: str, flat: str) -> Column:
    """array<struct<s,e,l,o,c>>: all detections in a column of lower-cased text, by place.

    ``flat`` is the text with each run of blanks as one. Both must be columns of their own: an expression would be evaluated again for every rule.
    """
    text = F.col(low)
    table = F.from_json(F.lit(json.dumps(rules())), _RULE)
    live = F.filter(table, lambda r: F.contains(F.col(flat), r["k2"]) & F.exists(r["k"], lambda k: F.contains(F.col(flat), k)))
    found = F.flatten(
        F.transform(live, lambda r: F.transform(matches(text, r["r"]), lambda m: F.struct(m["s"].alias("s"), m["e"].alias("e"), r["l"].alias("l"), r["o"].alias("o"), r["c"].alias("c"))))
    )
    return F.sort_array(F.array_distinct(found))


#: Detections that one pass of the sweep copies flags of.
BLOCK = 512


def unsuppressed(found: str) -> Column:
    """The detections in a column that lie in no longer one of their order or a higher one.

    A sweep by start, longest first: for each order it keeps the farthest end so far, with the farthest end of any
    other interval beside it, so that equal intervals of one order keep each other.
    """
    swept = F.array_sort(found, lambda x, y: _sign([x["s"] - y["s"], y["e"] - x["e"], x["o"] - y["o"], F.when(x["l"] < y["l"], -1).when(x["l"] > y["l"], 1).otherwise(0)]))
    orders = range(1 + max(r["o"] for r in rules()))
    none = F.struct(F.lit(-1).alias("s"), F.lit(-1).alias("e"), F.lit(-1).alias("e0"))
    zero = F.struct(*[none.alias(f"o{k}") for k in orders], F.lit("").alias("flags"))

    def step(acc: Column, d: Column) -> Column:
        hit, nxt = F.lit(False), []
        for k in orders:
            b = acc[f"o{k}"]
            same = (b["s"] == d["s"]) & (b["e"] == d["e"])
            other = F.when(same, b["e0"]).otherwise(b["e"])  # the farthest end of another interval
            hit |= (d["o"] == k) & (other >= d["e"]) | (d["o"] > k) & (b["e"] >= d["e"])
            far = F.struct(d["s"].alias("s"), d["e"].alias("e"), b["e"].alias("e0"))
            near = F.struct(b["s"].alias("s"), b["e"].alias("e"), F.when(same, b["e0"]).otherwise(F.greatest(b["e0"], d["e"])).alias("e0"))
            nxt.append(F.when(d["o"] != k, b).when(d["e"] > b["e"], far).otherwise(near).alias(f"o{k}"))
        return F.struct(*nxt, F.concat(acc["flags"], F.when(hit, "0").otherwise("1")).alias("flags"))

    def block(acc: Column, b: Column) -> Column:
        own = F.aggregate(b, F.struct(*[acc[f"o{k}"].alias(f"o{k}") for k in orders], F.lit("").alias("flags")), step)
        # one element, so that the block is swept once
        return F.element_at(F.transform(F.array(own), lambda x: F.struct(*[x[f"o{k}"].alias(f"o{k}") for k in orders], F.concat(acc["flags"], x["flags"]).alias("flags"))), 1)

    def keep(all_: Column) -> Column:
        blocks = F.transform(F.sequence(F.lit(0), F.size(all_) - 1, F.lit(BLOCK)), lambda k: F.slice(all_, k + 1, F.lit(BLOCK)))
        flags = F.split(F.aggregate(blocks, zero, block)["flags"], "")
        return F.transform(F.filter(F.arrays_zip(all_.alias("d"), F.slice(flags, F.lit(1), F.size(all_)).alias("f")), lambda x: x["f"] == "1"), lambda x: x["d"])

    return F.sort_array(F.flatten(F.transform(F.array(swept), keep)))


def _sign(parts: list[Column]) -> Column:
    """The first part that is not zero."""
    out = parts[-1]
    for x in reversed(parts[:-1]):
        out = F.when(x != 0, x).otherwise(out)
    return out


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, the contract's columns, and detections: array<struct<s,e,l,o,c>> of character places."""
    src = pick(docs, id_col, text_col).toDF("id", "text")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    low = src.select("id", text.alias("text"), F.lower(text).alias("low"))
    # no letter beyond ASCII lowers to a letter of the base phrases, so lower() serves for them
    norm = low.withColumn("norm", F.trim(F.regexp_replace("low", r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", " ")))
    count = lambda c, s: F.octet_length(c) - F.octet_length(F.replace(c, F.lit(s), F.lit("")))
    words = norm.withColumn("n_words", F.when(F.col("norm") == "", 0).otherwise(count(F.col("norm"), " ") + 1).cast("bigint"))
    padded = F.concat(F.lit(" "), F.col("norm"), F.lit(" "))
    has = [F.contains(padded, F.lit(f" {p} ")) for p in BASE]
    any_base = has[0] | has[1] | has[2] | has[3]
    # each word between two blanks of its own, so that neighbouring places share none
    words = words.withColumn("wide", F.when(any_base, F.replace(padded, F.lit(" "), F.lit("  "))))
    words = words.withColumn("ascii", F.when(reduce(Column.__or__, [F.contains(F.col("low"), F.lit(g)) for g in _GATE]), lower_ascii(F.col("text"))))
    words = words.withColumn("flat", F.regexp_replace("ascii", r"\s+", " "))
    none = F.array().cast("array<struct<s:int,e:int,l:string,o:int,c:double>>")
    words = words.withColumn("found", F.when(F.col("ascii").isNotNull(), detections("ascii", "flat")))
    wide, per = F.col("wide"), {}
    for p in BASE:
        key = " " + p.replace(" ", "  ") + " "
        per[p] = (
            (count(wide, key) / len(key)).cast("bigint"),
            (count(F.substring_index(wide, key, 1), " ") / 2).cast("bigint"),
            F.col("n_words") - (count(F.substring_index(wide, key, -1), " ") / 2).cast("bigint") - len(p.split()),
        )
    n_base = sum((F.coalesce(c, F.lit(0)) for c, _, _ in per.values()), F.lit(0).cast("bigint"))
    first = F.array_min(F.array(*[F.when(c > 0, f) for c, f, _ in per.values()]))
    last = F.array_max(F.array(*[F.when(c > 0, e) for c, _, e in per.values()]))
    base = F.array_sort(F.array_compact(F.array(*[F.when(per[p][0] > 0, F.lit(v)) for p, v in BASE.items()])))
    out = words.select(
        F.col("id").alias(id_col), "n_words", n_base.alias("n_base"), first.alias("first_word"), last.alias("last_word"), base.alias("b"),
        F.when(F.size("found") > 0, unsuppressed("found")).otherwise(none).alias("detections"),
    )
    labels = F.array_sort(F.array_distinct(F.concat("b", F.transform("detections", lambda d: d["l"]))))
    best = F.aggregate("detections", F.lit(0.0), lambda a, d: F.greatest(a, d["c"]))
    return out.select(
        id_col, "n_words", "n_base", "first_word", "last_word", F.array_join("b", ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"),
        F.greatest(best, F.when(F.col("n_base") > 0, 0.7).otherwise(0.0)).alias("score"), "detections",
    )
