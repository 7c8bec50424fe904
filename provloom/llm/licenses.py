"""License scan: phrases, and licence templates found by diagonal voting.

All rolling k-word hashes of the documents are joined to the positions of the same hashes in the templates (a fixed
table of some thousand rows, broadcast). Hits vote for (document, template, diagonal), the diagonal being document
position less template position. Diagonals that lie within ``drift`` of each other merge into one span; a span counts
if the template words it covers are at least ``similarity`` of the template and it isn't stretched beyond that.

Defined cases: null texts have no words, labels or spans and score 0; a text of fewer than k words has no template;
repeated rows give repeated result rows (their votes are distinct places, so they count once); an empty table gives an
empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provloom.llm.common import alnum_words, beside, keyed

#: Hashes that a task holds before it sends them on.
CHUNK = 100_000

# Phrases and their labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

# The wording of public licences and licence notices.
TEMPLATES = {
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "gpl-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions",
    "unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "cc-by": "This work is licensed under a Creative Commons Attribution 4.0 International License. To view a copy of this license, visit http://creativecommons.org/licenses/by/4.0/",
    "cc-by-sa": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License. To view a copy of this license, visit http://creativecommons.org/licenses/by-sa/4.0/",
}

# One-line notices, templates of their own (at least the five words of a hash); the label ends at the colon.
TEMPLATES |= {
    "mit:released": "Released under the MIT License",
    "mit:licensed": "Licensed under the MIT License",
    "bsd:released": "Released under the BSD License",
    "bsd:licensed": "Licensed under the BSD License",
    "apache-2.0:released": "Released under the Apache License, Version 2.0",
    "apache-2.0:licensed": "Licensed under the Apache License, Version 2.0",
    "mpl-2.0:licensed": "Licensed under the Mozilla Public License, Version 2.0",
    "gpl:licensed": "Licensed under the GNU General Public License, version 3",
    "cc-by:licensed": "Licensed under CC BY 4.0",
    "cc-by-sa:licensed": "Licensed under CC BY-SA 4.0",
    "cc-by-nc:licensed": "Licensed under CC BY-NC 4.0",
}


def word_hashes(words: list[bytes], cache: dict[bytes, int]) -> np.ndarray:
    """64-bit hashes of the words; cache keeps those seen."""
    if len(cache) > 500_000:
        cache.clear()
    out = []
    for w in words:
        if (h := cache.get(w)) is None:
            h = cache[w] = xxhash.xxh3_64_intdigest(w)
        out.append(h)
    return np.array(out, np.uint64)


def rolling(hashes: np.ndarray, k: int) -> np.ndarray:
    """A 64-bit hash of each k consecutive words."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for i in range(k):
        out = out * np.uint64(0x9E3779B97F4A7C15) + hashes[i : i + n]
        out ^= out >> np.uint64(29)
    return out


def phrase_places(words: list[bytes]) -> tuple[list[int], list[str]]:
    """Starts of all phrase occurrences, and the labels found."""
    joined, starts, labels = b" " + b" ".join(words) + b" ", [], set()
    for phrase, label in PHRASES.items():
        needle = b" " + phrase.encode() + b" "
        at = joined.find(needle)
        while at >= 0:
            starts.append(joined.count(b" ", 0, at))
            labels.add(label)
            at = joined.find(needle, at + 1)
    return sorted(starts), sorted(labels)


def base_scan(docs: DataFrame) -> DataFrame:
    """doc_id, tkey, n_words, n_base, first_word, last_word, base_labels per row."""

    def one(text):
        words = alnum_words(text)
        starts, labels = phrase_places(words)
        return len(words), len(starts), starts[0] if starts else None, starts[-1] if starts else None, ",".join(labels)

    d = keyed(docs).withColumn("tkey", F.xxhash64("text"))
    return beside(d, ["doc_id", "tkey"], ["text"], lambda: lambda texts: [one(t) for t in texts], "n_words long, n_base long, first_word long, last_word long, base_labels string")


def template_positions(spark, templates: dict[str, str], k: int) -> DataFrame:
    rows = []
    for name, text in templates.items():
        words = alnum_words(text)
        rows += [(int(h), name, i, len(words)) for i, h in enumerate(rolling(word_hashes(words, {}), k).view(np.int64))]
    return spark.createDataFrame(rows, "h long, template string, tpos int, twords int")


def spans(docs: DataFrame, templates: dict[str, str] | None = None, k: int = 5, similarity: float = 0.8, drift: int = 3) -> DataFrame:
    """(doc_id, tkey, template, first, last, similarity): verified template spans, words from 0."""

    def run(batches):
        cache: dict[bytes, int] = {}
        ids, keys, pos, grams, held = [], [], [], [], 0

        def rows():
            n = [len(g) for g in grams]
            at = pa.array(np.repeat(np.arange(len(n)), n))
            columns = [pa.array(ids, pa.int64()).take(at), pa.array(keys, pa.int64()).take(at), pa.array(np.concatenate(pos)), pa.array(np.concatenate(grams))]
            return pa.RecordBatch.from_arrays(columns, ["doc_id", "tkey", "pos", "h"])

        for b in batches:
            for doc_id, tkey, text in zip(b.column("doc_id").to_pylist(), b.column("tkey").to_pylist(), b.column("text")):
                h = rolling(word_hashes(alnum_words(text.as_py()), cache), k).view(np.int64)
                for lo in range(0, len(h), CHUNK):  # a long text leaves in parts, too
                    part = h[lo : lo + CHUNK]
                    ids.append(doc_id)
                    keys.append(tkey)
                    pos.append(np.arange(lo, lo + len(part), dtype=np.int32))
                    grams.append(part)
                    held += len(part)
                    if held >= CHUNK:
                        yield rows()
                        ids, keys, pos, grams, held = [], [], [], [], 0
        if held:
            yield rows()

    d = keyed(docs).withColumn("tkey", F.xxhash64("text"))
    grams = d.mapInArrow(run, "doc_id long, tkey long, pos int, h long")
    hits = grams.join(F.broadcast(template_positions(docs.sparkSession, templates or TEMPLATES, k)), "h")
    votes = hits.groupBy("doc_id", "tkey", "template", "twords", (F.col("pos") - F.col("tpos")).alias("diagonal")).agg(
        F.collect_set("tpos").alias("tposs"), F.min("pos").alias("lo"), F.max("pos").alias("hi")
    )
    w = Window.partitionBy("doc_id", "tkey", "template").orderBy("diagonal")
    votes = votes.withColumn("new", (F.col("diagonal") - F.lag("diagonal").over(w) > drift).cast("int"))
    votes = votes.withColumn("span", F.sum(F.coalesce("new", F.lit(1))).over(w))
    merged = votes.groupBy("doc_id", "tkey", "template", "twords", "span").agg(
        F.flatten(F.collect_list("tposs")).alias("tposs"), F.min("lo").alias("first"), (F.max("hi") + k - 1).alias("last")
    )
    covered = F.expr(f"size(array_distinct(flatten(transform(tposs, t -> sequence(t, t + {k - 1})))))")
    merged = merged.withColumn("covered", covered).withColumn("similarity", F.col("covered") / F.greatest("twords", F.col("last") - F.col("first") + 1))
    return merged.where(F.col("similarity") >= similarity).select("doc_id", "tkey", "template", "first", "last", "similarity")


def scan(docs: DataFrame, **how) -> DataFrame:
    """Per row: the base measures, labels (phrases and templates), score (1 for a phrase, else the best similarity)."""
    base = base_scan(docs)
    found = spans(docs, **how).groupBy(F.col("doc_id").alias("fid"), F.col("tkey").alias("fkey")).agg(
        F.collect_set(F.split("template", ":")[0]).alias("templates"), F.max("similarity").alias("best")
    )
    all_labels = F.expr("array_sort(array_distinct(concat(coalesce(templates, array()), filter(split(base_labels, ','), x -> x <> ''))))")
    return (
        base.join(found, (base["tkey"] == found["fkey"]) & base["doc_id"].eqNullSafe(found["fid"]), "left")
        .withColumn("labels", F.array_join(all_labels, ","))
        .withColumn("score", F.when(F.col("n_base") > 0, 1.0).otherwise(F.least(F.coalesce("best", F.lit(0.0)), F.lit(1.0))))
        .select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")
    )
