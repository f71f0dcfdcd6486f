"""License scans by diagonal voting.

A text is its ASCII-lower-cased words. Every rolling k-gram of words is sought among the k-grams of
a small library of license wordings, and those that occur there are joined to their template
positions. A hit votes for the diagonal (place in the text minus place in the template); votes are
counted per document and diagonal, neighbouring diagonals of one template are merged (words put in
or left out shift the diagonal), and the words around the strongest diagonal of each merged hit are
aligned in order with the template.

Words are looked up once, a block of texts at a time; a gram is the number its words' places in the
library's vocabulary spell, so equal numbers are equal words. Hits go on as rows with the few words
around them, so a text's length bounds no row.

Defined results: null texts count as empty; a document without words has no places and null
first_word and last_word; repeated rows give one result row each; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from unionlake.llm.common import checkpointed, light, portions
from unionlake.llm.decontaminate import FOLD

#: Phrases whose exact places are counted, with their labels.
BASE = [("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc")]

#: Wordings of public licenses and notices that the method recognises besides, in whole or in part,
#: and the word without which a part of it is not taken for that license.
WORDINGS = [
    ("released under the mit license", "mit", "mit"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit", "permission"),
    ("licensed under the apache license version 2 0", "apache-2", "apache"),
    ("you may not use this file except in compliance with the license you may obtain a copy of the license at", "apache-2", "compliance"),
    ("licensed under cc by nc 4 0", "cc-by-nc", "nc"),
    ("creative commons attribution noncommercial 4 0 international", "cc-by-nc", "noncommercial"),
    ("creative commons attribution sharealike 4 0 international", "cc-by-sa", "sharealike"),
    ("licensed under the gnu general public license version 3", "gpl-3", "3"),
    ("licensed under the gnu general public license version 2", "gpl-2", "2"),
    ("gnu lesser general public license", "lgpl", "lesser"),
    ("gnu affero general public license", "agpl", "affero"),
    ("mozilla public license version 2 0", "mpl-2", "mozilla"),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that", "bsd", "redistribution"),
    ("this is free and unencumbered software released into the public domain", "unlicense", "this"),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc", "permission"),
    ("the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "mit", "substantial"),
    ("unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis", "apache-2", "basis"),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3", "gpl-3", "3"),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2", "gpl-2", "2"),
    ("this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license", "lgpl", "lesser"),
    ("under the terms of the gnu affero general public license as published by the free software foundation", "agpl", "affero"),
    ("this source code form is subject to the terms of the mozilla public license v 2 0", "mpl-2", "mozilla"),
    ("neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software", "bsd", "endorse"),
    ("redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation", "bsd", "reproduce"),
    ("the software is provided as is and the author disclaims all warranties with regard to this software", "isc", "disclaims"),
    ("this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages", "zlib", "held"),
    ("anyone is free to copy modify publish use compile sell or distribute this software", "unlicense", "anyone"),
    ("boost software license version 1 0", "boost", "boost"),
]


FOUND = "row_id bigint, doc_id bigint, n_words bigint, pos bigint, gram bigint, low bigint, around array<smallint>"


def templates() -> list[list[str]]:
    return [x[0].split() for x in BASE + WORDINGS]


class Library:
    """The words and k-grams of all templates."""

    def __init__(self, k: int):
        self.k, self.templates = k, templates()
        if min(map(len, self.templates)) < k:
            raise ValueError(f"every template needs {k} words")
        self.words = sorted({w for t in self.templates for w in t})
        place = {w: i for i, w in enumerate(self.words, 1)}
        self.numbers = [[place[w] for w in t] for t in self.templates]
        self.base = len(self.words) + 1
        if self.base**k >= 1 << 63:
            raise ValueError(f"{k}-grams of {len(self.words)} words do not fit a long")
        self.longest = max(map(len, self.templates))

    def gram(self, words: list[int]) -> int:
        out = 0
        for w in words:
            out = out * self.base + w
        return out

    def positions(self) -> list[tuple[int, int, int, int]]:
        """(template, place, gram, length of the template)."""
        return [(t, i, self.gram(n[i : i + self.k]), len(n)) for t, n in enumerate(self.numbers) for i in range(len(n) - self.k + 1)]


def numbered(texts: pa.Array, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The place in `words` (from 1; else 0) of each word of all texts, and where each text's words begin, with the end."""
    raw = [(t or "").encode("utf-8", "replace") for t in texts.to_pylist()]
    joined = np.frombuffer(b" ".join(raw).translate(FOLD), np.uint8)
    inside = joined != 32
    edges = np.flatnonzero(np.diff(np.concatenate(([False], inside, [False])).view(np.int8)))
    starts, ends = edges[::2], edges[1::2]
    offsets = np.zeros(len(starts) + 1, np.int32)
    np.cumsum(ends - starts, out=offsets[1:])
    every = pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(offsets), pa.py_buffer(joined[inside])])
    place = pc.fill_null(pc.add(pc.index_in(every, value_set=words), 1), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    firsts = np.concatenate(([0], np.cumsum(np.fromiter(map(len, raw), np.int64, len(raw)) + 1)))
    return place, np.searchsorted(starts, firsts)


def found(docs: DataFrame, library: Library, slack: int, batch_rows: int = 100_000) -> DataFrame:
    """A row for each document, with its number of words, and for each k-gram that the library knows, with the words around it."""
    k, reach = library.k, library.longest + slack
    names = [f.split()[0] for f in FOUND.split(", ")]

    def run(batches):
        from pyspark import TaskContext

        words = pa.array([w.encode() for w in library.words], pa.binary())
        known = np.unique(np.array([g for _, _, g, _ in library.positions()], np.int64))
        row_id = TaskContext.get().partitionId() << 36
        none = lambda n, kind: pa.nulls(n, kind)
        lists = pa.list_(pa.int16())
        for batch in batches:
            for part in portions(batch, 1):
                place, bounds = numbered(part.column(1), words)
                n = part.num_rows
                ids = np.arange(row_id, row_id + n)
                row_id += n
                yield pa.RecordBatch.from_arrays([pa.array(ids), part.column(0), pa.array(np.diff(bounds)), *[none(n, pa.int64())] * 3, none(n, lists)], names)
                number = np.zeros(max(0, len(place) - k + 1), np.int64)
                whole = np.ones(len(number), bool)
                for j in range(k):
                    word = place[j : j + len(number)]
                    number = number * library.base + word
                    whole &= word > 0
                at = np.flatnonzero(whole)
                at = at[np.isin(number[at], known)]
                text = np.searchsorted(bounds, at, "right") - 1
                at, text = (x[at + k <= bounds[text + 1]] for x in (at, text))  # a gram does not reach into the next text
                for begin in range(0, len(at), batch_rows):
                    a, t = at[begin : begin + batch_rows], text[begin : begin + batch_rows]
                    low, high = np.maximum(a - reach, bounds[t]), np.minimum(a + k + reach, bounds[t + 1])
                    offsets = np.concatenate(([0], np.cumsum(high - low)))
                    take = np.repeat(low - offsets[:-1], high - low) + np.arange(offsets[-1])
                    around = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(place[take].astype(np.int16)))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[t]), none(len(a), pa.int64()), none(len(a), pa.int64()), pa.array(a - bounds[t]), pa.array(number[a]), pa.array(low - bounds[t]), around], names)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").select("doc_id", "text").mapInArrow(light(run), FOUND)


def votes(spark: SparkSession, hits: DataFrame, library: Library) -> DataFrame:
    """(row_id, template, diagonal, votes, length, exact, span): one row per document, template and diagonal with a hit.

    The library has a few hundred positions whatever the input, so it is broadcast. Where every gram
    of the template votes, its words stand there one after another.
    """
    lib = spark.createDataFrame(library.positions(), "template int, place bigint, gram bigint, length int")
    placed = hits.join(F.broadcast(lib), "gram").withColumn("diagonal", F.col("pos") - F.col("place"))
    counted = placed.groupBy("row_id", "template", "diagonal").agg(
        F.count("*").alias("votes"), F.first("length").alias("length"), F.min_by(F.struct("low", "around"), "pos").alias("span"),
    )
    return counted.withColumn("exact", F.col("votes") == F.col("length") - library.k + 1)


def common_length(a: list[int], b: list[int]) -> int:
    """How many words of a stand in b in the same order, at most: one bit a word of a, a step a word of b."""
    where: dict[int, int] = {}
    for i, w in enumerate(a):
        where[w] = where.get(w, 0) | 1 << i
    row = 0
    for w in b:
        x = row | where.get(w, 0)
        row = x & (x ^ (x - ((row << 1) | 1)))
    return row.bit_count()


def aligned(merged: DataFrame, library: Library, slack: int) -> DataFrame:
    """merged with `cover`: the share of its template that stands in order in the words around its strongest diagonal, and that the votes confirm."""
    must = [{w: i for i, w in enumerate(library.words, 1)}[x[2] if len(x) > 2 else x[0].split()[0]] for x in BASE + WORDINGS]
    schema = merged.drop("best").schema.add("cover", "double")
    at = {c: i for i, c in enumerate(merged.columns)}
    kept = [c for c in at if c != "best"]

    def run(batches):
        for batch in batches:
            rows = zip(*(batch.column(at[c]).to_pylist() for c in ("template", "exact", "votes", "best")), strict=True)
            out = []
            for t, exact, n, best in rows:
                own = library.numbers[t]
                first = best["diagonal"] - best["span"]["low"]
                span = best["span"]["around"][max(0, first - slack) : first + len(own) + slack]
                if exact:
                    out.append(1.0)
                elif must[t] not in span:
                    out.append(0.0)
                else:
                    cover = common_length(own, span) / len(own)
                    out.append(min(cover, (cover + min(1.0, n / (len(own) - library.k + 1))) / 2))
            yield pa.RecordBatch.from_arrays([*(batch.column(at[c]) for c in kept), pa.array(out, pa.float64())], [*kept, "cover"])

    return merged.mapInArrow(light(run), schema)


def scan(spark: SparkSession, docs: DataFrame, k: int = 3, slack: int = 3, least: float = 0.6) -> DataFrame:
    """One row per document: places of the base phrases, base labels, all labels and the best coverage as score.

    A template is recognised where the words of a verified merged span cover at least `least` of it.
    """
    library = Library(k)
    rows = checkpointed(spark, found(docs, library, slack), "licenses")
    counted = votes(spark, rows.where("gram is not null").select("row_id", "pos", "gram", "low", "around"), library)
    # runs of diagonals of one template that lie within slack of each other are one merged hit
    order = Window.partitionBy("row_id", "template").orderBy("diagonal")
    fresh = (F.col("diagonal") - F.lag("diagonal").over(order) > slack) | F.lag("diagonal").over(order).isNull()
    counted = counted.withColumn("run", F.sum(F.when(fresh, 1).otherwise(0)).over(order))
    merged = counted.groupBy("row_id", "template", "run").agg(
        F.sum("votes").alias("votes"),
        F.count_if("exact").alias("exact"),
        F.min(F.when(F.col("exact"), F.col("diagonal"))).alias("first"),
        F.max(F.when(F.col("exact"), F.col("diagonal"))).alias("last"),
        F.max_by(F.struct("diagonal", "span"), F.struct("votes", -F.col("diagonal"))).alias("best"),
    )
    label = spark.createDataFrame([(t, x[1]) for t, x in enumerate(BASE + WORDINGS)], "template int, label string")
    seen = aligned(merged, library, slack).join(F.broadcast(label), "template")
    base = F.col("template") < len(BASE)
    joined = lambda on: F.array_join(F.array_sort(F.collect_set(F.when(on, F.col("label")))), ",")
    per = seen.groupBy("row_id").agg(
        F.sum(F.when(base, F.col("exact"))).alias("n_base"),
        F.min(F.when(base, F.col("first"))).alias("first_word"),
        F.max(F.when(base, F.col("last"))).alias("last_word"),
        joined(base & (F.col("exact") > 0)).alias("base_labels"),
        joined((base & (F.col("exact") > 0)) | (~base & (F.col("cover") >= least))).alias("labels"),
        F.max("cover").alias("score"),
    )
    every = rows.where("gram is null").select("row_id", "doc_id", "n_words").join(per, "row_id", "left")
    return every.select(
        "doc_id", "n_words", F.coalesce("n_base", F.lit(0)).alias("n_base"), "first_word", "last_word",
        F.coalesce("base_labels", F.lit("")).alias("base_labels"), F.coalesce("labels", F.lit("")).alias("labels"), F.coalesce("score", F.lit(0.0)).alias("score"),
    )
