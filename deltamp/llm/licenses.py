"""License scans in DataFrame expressions: MinHash bands retrieve templates, shingle containment verifies.

A document's 5-word shingles are hashed once. A template of n words belongs to the least window width w (a
power of two, 8 or more) with n <= w/2 + 1; windows of a width start at every half width, so the notice lies
whole in one of them. Windows are cut where the document has a shingle of some template of that width (a bit
per hash prefix, then the hash itself): others share nothing with these templates. With BANDS bands of one
row, a window that contains 0.8 of a template of its width has a similarity of 0.16 or more and misses all bands
with a chance under 1e-7. Candidates are kept if the window holds at least 0.8 of the template's shingles.
Templates may be of any length, whole licence texts included; their table is broadcast after a check of its
size (MOST_SHINGLES).

Defined results: null or short texts match nothing; a template under 5 words is an error; repeated rows merge
into one row per id and template; a null id is an id; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.llm.common import lower_ascii

SHINGLE, LEAST, BANDS = 5, 0.8, 96
LEAST_WIDTH, MOST_SHINGLES = 8, 200_000
_WORD = r"[a-z0-9]+(?:[.-][a-z0-9]+)*"
# Short public notices, by licence.
TEMPLATES = {
    "Apache-2.0": ("Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License."),
    "MIT": (
        "Released under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    "ISC": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",),
    "GPL-3.0": ("This work is licensed under the GNU General Public License, version 3.",),
    "GPL-2.0": ("This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License version 2.",),
    "BSD-3-Clause": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met.",),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.",),
    "CC-BY-4.0": ("Licensed under CC BY 4.0 International.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
}


def _words(text: Column) -> Column:
    return F.regexp_extract_all(lower_ascii(F.coalesce(text.cast("string"), F.lit(""))), F.lit(_WORD), F.lit(0))


def _shingles(words: str) -> Column:
    n = F.size(words) - (SHINGLE - 1)
    make = lambda i: F.xxhash64(*[F.get(F.col(words), i + k) for k in range(SHINGLE)])
    return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), make)).otherwise(F.array().cast("array<bigint>"))


def _bands(shingles: Column) -> Column:
    least = lambda j: F.array_min(F.transform(shingles, lambda x: F.xxhash64(x, F.lit(j))))
    return F.array(*[F.struct(F.lit(j).alias("band"), least(j).alias("low")) for j in range(BANDS)])


def width_of(words: int) -> int:
    """The least power of two w, LEAST_WIDTH or more, with words <= w / 2 + 1."""
    return max(LEAST_WIDTH, 1 << (2 * (words - 1) - 1).bit_length())


def templates(spark: SparkSession, texts: dict[str, tuple[str, ...]] = TEMPLATES) -> DataFrame:
    """template, license, width, shingles: one row per template, a table of checked size."""
    rows, total = [], 0
    for name, notices in texts.items():
        for k, t in enumerate(notices):
            n = len(re.findall(_WORD, t.lower()))
            if n < SHINGLE:
                raise ValueError(f"{name}/{k}: a template needs {SHINGLE} words or more")
            total += n
            rows.append((f"{name}/{k}", name, width_of(n), t))
    if total > MOST_SHINGLES:
        raise ValueError("the templates are over MOST_SHINGLES words: scan for them in parts")
    made = spark.createDataFrame(rows, "template string, license string, width int, text string")
    return made.withColumn("words", _words(F.col("text"))).select("template", "license", "width", F.array_distinct(_shingles("words")).alias("shingles"))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", texts: dict[str, tuple[str, ...]] = TEMPLATES) -> DataFrame:
    """Per id and template: license, containment (the best window's share) and first_word (where it starts)."""
    spark = docs.sparkSession
    wanted = templates(spark, texts)
    filed = wanted.select("width", "shingles").collect()  # some shingles a template
    widths = sorted({r["width"] for r in filed})
    hashes = {w: sorted({h for r in filed if r["width"] == w for h in r["shingles"]}) for w in widths}
    prefixes = {(h >> 48) & 0xFFFF for own in hashes.values() for h in own}
    bits = F.split(F.lit(",".join("1" if i in prefixes else "0" for i in range(1 << 16))), ",").cast("array<tinyint>")
    every = F.array(*[F.lit(h) for h in sorted(set().union(*hashes.values()))])
    narrow = docs.select(F.col(id_col).alias("id"), _words(F.col(text_col)).alias("words")).select("id", _shingles("words").alias("h"))
    maybe = F.filter(F.transform("h", lambda x, i: F.when((F.get(bits, F.shiftrightunsigned(x, 48).cast("int")) == 1) & F.array_contains(every, x), i)), lambda i: i.isNotNull())
    # explode_outer: no filter is inferred that the optimiser would push down, and the arrays with it.
    hit = narrow.select("id", "h", maybe.alias("hits"))

    def placed(w: int) -> Column:
        """The windows of width w over the hits of templates of that width."""
        mine = F.filter("hits", lambda p: F.array_contains(F.array(*[F.lit(x) for x in hashes[w]]), F.get(F.col("h"), p)))
        starts = F.flatten(F.transform(mine, lambda p: F.array(F.floor(p / (w // 2)) * (w // 2), (F.floor(p / (w // 2)) - 1) * (w // 2))))
        return F.transform(F.array_distinct(starts), lambda s: F.struct(F.lit(w).alias("width"), s.cast("int").alias("at")))

    spans = F.concat(*[placed(w) for w in widths])
    windows = hit.select("id", "h", F.explode_outer(spans).alias("s")).where("s.at >= 0")
    windows = windows.select("id", F.col("s.width").alias("width"), F.col("s.at").alias("at"), F.array_distinct(F.slice("h", F.col("s.at") + 1, F.col("s.width") - (SHINGLE - 1))).alias("have"))
    signed = windows.select("id", "width", "at", "have", F.explode_outer(_bands(F.col("have"))).alias("b")).select("id", "width", "at", "have", "b.band", "b.low")
    filed = wanted.select("template", "license", "width", "shingles", F.explode(_bands(F.col("shingles"))).alias("b")).select("template", "license", "width", "shingles", "b.band", "b.low")
    met = signed.join(F.broadcast(filed), ["width", "band", "low"])  # BANDS rows a template: bounded
    share = F.size(F.array_intersect("have", "shingles")) / F.size("shingles")
    best = met.select("id", "template", "license", "at", share.alias("containment")).where(F.col("containment") >= LEAST)
    found = best.groupBy("id", "template", "license").agg(F.max(F.struct("containment", (-F.col("at")).alias("at"))).alias("m"))
    return found.select(F.col("id").alias(id_col), "template", "license", F.col("m.containment").alias("containment"), (-F.col("m.at")).alias("first_word"))
