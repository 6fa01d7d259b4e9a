"""Operator 9: license texts found by MinHash bands over text windows, DataFrame functions only.

Text and templates become lower-case words of letters and digits, and sets of
shingles (five words in a row, hashed).  Windows of a document are compared
with templates: for each width class, windows of one and a half times the width
start every half width (short classes: windows of the width start at every
word), so any occurrence of a template lies in a window of its class.  A
window's signature is the least hash under each of `bands` seeds, each a band
of its own: with 32 bands a window whose similarity to the template is a third
or more (what an occurrence has at least) shares a band with it with
probability above 1 - 3e-6.  Retrieved pairs are verified: the share of the
template's shingles that the window holds must reach `containment`.

Only windows that can match are hashed, without loss: from each template words
are picked so that over 1 - containment of its shingles hold a picked one; a
window without any picked word is below the containment, and a document whose
text does not contain one as a substring is not split at all.

Templates are a constant below, a list, or a frame (license, text) of any size.
They are taken `MOST_TEMPLATES` at a time, so that what is broadcast is bounded;
documents are read once for each such block.  Documents are not shuffled; only
verified matches are grouped.

A null or empty text has no match.  A template of fewer than five words is one
shingle of all its words and is found where they stand in a row.  One row per
(document id, license): best containment, first word of the best window (the
earliest on ties), windows that match.  Rows with a null id are reported
together under the null id; repeated ids likewise.  Of a very long text only the
windows around marked words are made, each a row of its own.  Empty tables of
either kind give no rows.  Other columns, whatever their names, are not read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

SHINGLE, BANDS, CONTAINMENT = 5, 32, 0.8
#: Classes up to this width have a window at every word.
SHORT = 16
MOST_TEMPLATES = 10_000

# Short statements and permission texts of public licenses.
TEMPLATES = [
    ("MIT", "Released under the MIT License."),
    ("MIT", "This project is licensed under the terms of the MIT license."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0-or-later", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0-or-later", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."),
]


def words_of(text: str) -> list[str]:
    return re.findall("[a-z0-9]+", text.lower())


def width_class(n: int) -> int:
    """Width of the class for templates of n words: itself if short, else the next power of the root of two."""
    return n if n <= SHORT else math.ceil(SHORT * math.sqrt(2) ** math.ceil(2 * math.log2(n / SHORT) - 1e-9))


def picked_words(templates: list[tuple[str, str]], containment: float) -> list[str]:
    """Words such that a text without any holds less than `containment` of any template's shingles."""
    picked: set[str] = set()
    for _, text in templates:
        words = words_of(text)
        k = min(SHINGLE, len(words))
        rows = list(dict.fromkeys(tuple(words[i : i + k]) for i in range(len(words) - k + 1)))
        while rows and sum(bool(picked & {*r}) for r in rows) <= (1 - containment) * len(rows) + 1e-9:
            left = [r for r in rows if not picked & {*r}]
            # long words are rare; one that many of the open shingles hold serves best
            picked.add(max({w for r in left for w in r}, key=lambda w: (min(len(w), 8) * sum(w in r for r in left), w)))
    return sorted(picked)


def _hashes(words: Column, k: int) -> Column:
    """Hash of each k words in a row, and of all words if there are fewer."""
    n = F.size(words)
    many = F.transform(F.sequence(F.lit(1), n - (k - 1)), lambda i: F.xxhash64(*[F.get(words, i + (j - 1)) for j in range(k)]))
    return F.when(n >= k, many).otherwise(F.expr("cast(array() as array<bigint>)"))


def _split(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), "[^a-z0-9]+"), "")


def _band_keys(shingles: Column, bands: int) -> Column:
    def key(b: int) -> Column:
        return F.xxhash64(F.lit(b), F.array_min(F.transform(shingles, lambda s: F.xxhash64(s, F.lit(b)))))

    return F.array(*[key(b) for b in range(bands)])


def _windows(width: int, k: int) -> Column:
    """Grid windows of a class that hold a marked word, as structs (width, k, start, span)."""
    step = 1 if width <= SHORT else width // 2
    span = width if width <= SHORT else width + step + step % 2

    def around(p: Column) -> Column:
        first, last = F.greatest(F.lit(0), F.ceil((p - (span - 1)) / step)), F.floor(p / step)
        return F.transform(F.sequence(first.cast("int"), last.cast("int")), lambda g: g * step)

    starts = F.array_distinct(F.flatten(F.transform("at", around)))
    return F.transform(starts, lambda s: F.struct(F.lit(width).alias("width"), F.lit(k).alias("k"), s.alias("start"), F.lit(span).alias("span")))


def template_frame(spark: SparkSession, templates: list[tuple[str, str]], bands: int) -> DataFrame:
    """Rows (license, width, k, shingles, keys), made by the same expressions as the documents'."""
    rows = [(name, width_class(len(words_of(t))), min(SHINGLE, len(words_of(t))), " ".join(words_of(t))) for name, t in templates if words_of(t)]
    structs = [F.struct(F.lit(a).alias("license"), F.lit(b).alias("width"), F.lit(c).alias("k"), F.lit(d).alias("t")) for a, b, c, d in rows]
    t = spark.range(1).select(F.explode(F.array(*structs)).alias("x")).select("x.*")
    by_k = F.coalesce(*[F.when(F.col("k") == k, _hashes(_split(F.col("t")), k)) for k in sorted({r[2] for r in rows})])
    t = t.select("license", "width", "k", F.array_distinct(by_k).alias("wanted"))
    return t.withColumn("keys", _band_keys(F.col("wanted"), bands))


def _taken(templates: DataFrame | list[tuple[str, str]] | None) -> Iterator[list[tuple[str, str]]]:
    """Templates with a word, in blocks of bounded size."""
    if isinstance(templates, DataFrame):
        t = templates.select(F.col(templates.columns[0]).cast("string").alias("a"), F.col(templates.columns[1]).alias("b")).where("b is not null")
        n = math.ceil(t.count() / MOST_TEMPLATES)
        for k in range(n):
            yield [(r["a"], r["b"]) for r in t.where(F.pmod(F.xxhash64("a", "b"), F.lit(n)) == k).collect() if words_of(r["b"])]
    else:
        known = [(a, b) for a, b in (TEMPLATES if templates is None else templates) if words_of(b)]
        for k in range(0, len(known), MOST_TEMPLATES):
            yield known[k : k + MOST_TEMPLATES]


def scan(docs: DataFrame, templates: DataFrame | list[tuple[str, str]] | None = None, containment: float = CONTAINMENT, bands: int = BANDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, license, containment, first_word, windows) of documents that hold a license text."""
    blocks = [_matches(docs, block, containment, bands, id_col, text_col) for block in _taken(templates) if block]
    if not blocks:
        return docs.sparkSession.createDataFrame([], "doc_id long, license string, containment double, first_word int, windows long")
    got = reduce(DataFrame.union, blocks).groupBy("doc_id", "license", "width", "start").agg(F.max("share").alias("share"))
    best = F.max(F.struct(F.col("share"), (-F.col("start")).alias("first")))
    got = got.groupBy("doc_id", "license").agg(best.alias("best"), F.count("*").alias("windows"))
    return got.select("doc_id", "license", F.col("best.share").alias("containment"), (-F.col("best.first")).alias("first_word"), "windows")


def _matches(docs: DataFrame, templates: list[tuple[str, str]], containment: float, bands: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (doc_id, license, width, start, share) of windows that hold a template of a block."""
    spark = docs.sparkSession
    picked = picked_words(templates, containment)
    lower = F.lower(F.col(text_col))
    may = F.lit(False)
    for w in picked:
        may = may | lower.contains(w)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("t")).where(may)
    rows = rows.select("doc_id", _split(F.col("t")).alias("words"))
    rows = rows.where(F.arrays_overlap("words", F.array(*[F.lit(w) for w in picked])))
    marked = F.filter(F.transform("words", lambda w, i: F.when(w.isin(picked), i)), lambda i: i.isNotNull())
    rows = rows.withColumn("at", marked)
    kinds = sorted({(width_class(len(words_of(t))), min(SHINGLE, len(words_of(t)))) for _, t in templates})
    per_kind = [_windows(width, k) for width, k in kinds]
    rows = rows.select("doc_id", "words", F.explode(F.concat(*per_kind)).alias("w"))
    rows = rows.select("doc_id", "w.*", F.slice("words", F.col("w.start") + 1, F.col("w.span")).alias("words"))
    by_k = F.coalesce(*[F.when(F.col("k") == k, _hashes(F.col("words"), k)) for k in sorted({k for _, k in kinds})])
    rows = rows.select("doc_id", "width", "k", "start", F.array_distinct(by_k).alias("shingles")).where(F.size("shingles") > 0)
    keyed = rows.select("*", F.explode(F.array_distinct(_band_keys(F.col("shingles"), bands))).alias("key"))
    t = template_frame(spark, templates, bands).select("license", F.col("width").alias("tw"), F.col("k").alias("tk"), "wanted", F.explode("keys").alias("tkey"))
    got = keyed.join(F.broadcast(t), (F.col("key") == F.col("tkey")) & (F.col("width") == F.col("tw")) & (F.col("k") == F.col("tk")))
    share = F.size(F.array_intersect("wanted", "shingles")) / F.size("wanted")
    return got.select("doc_id", "license", "width", "start", share.alias("share")).where(F.col("share") >= containment)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(base.table(spark, sf_dir, "documents"))
