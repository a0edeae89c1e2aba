"""License scans by diagonal voting, in DataFrame operations only.

Every run of k words of a text is hashed and joined with the template positions that hold the same run. A hit votes for
the diagonal text position - template position; neighbouring diagonals (a word more or less) are merged, and the
merged diagonal's span is verified: enough of the template's positions are hit, and they are dense within the span.

The templates are a fixed list of short notices (under 1,000 runs), broadcast whatever the corpus; texts without any
hit are dropped before their runs become rows, and votes are aggregated by text, template and diagonal before a shuffle.

Defined cases: null text counts as empty; repeated rows stay rows; empty tables give empty results.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathweave.llm import common as C

K, NEAR, MIN_COVER, MIN_DENSE = 4, 3, 0.6, 0.5
_SEP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Phrases of the base scan and their labels.
PHRASES = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))
#: Public licence notices.
TEMPLATES = (
    ("mit", "Released under the MIT License."),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions"),
    ("apache-2", "Licensed under the Apache License, Version 2.0."),
    ("apache-2", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    ("apache-2", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("bsd", "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED."),
    ("mit", "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT."),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-nc", "Licensed under CC BY-NC 4.0."),
    ("cc-by-nc", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("cc-by-sa", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("gpl-3", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    ("lgpl", "you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation"),
    ("mpl-2", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("unlicense", "This is free and unencumbered software released into the public domain."),
)


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(C.ascii_lower(text), _SEP), "")


def runs(words: Column, k: int) -> Column:
    """Hashes of the runs of k words."""
    hashed = lambda w: F.transform(F.sequence(F.lit(0), F.size(w) - k), lambda i: F.xxhash64(*[F.get(w, i + j) for j in range(k)]))
    return F.when(F.size(words) < k, F.array().cast("array<long>")).otherwise(F.get(F.transform(F.array(words), hashed), F.lit(0)))


def templates(spark: SparkSession, texts=TEMPLATES, k: int = K) -> DataFrame:
    """(template, label, size, at, run): the runs of every template; shorter templates are not kept."""
    rows = [(t, label, text) for t, (label, text) in enumerate(texts)]
    t = spark.createDataFrame(rows, "template int, label string, text string")
    t = t.withColumn("runs", runs(words_of(F.col("text")), k)).withColumn("size", F.size("runs"))
    return t.select("template", "label", "size", F.posexplode("runs").alias("at", "run"))


def _fold(phrase: str) -> list[str]:
    return [w for w in re.split(_SEP, phrase.lower()) if w]


def base(line: Column, phrases=PHRASES) -> dict[str, Column]:
    """Counts, ends and labels of the phrases in a line of words (a blank before and after each)."""
    framed = [(" " + " ".join(_fold(p)) + " ", label) for p, label in phrases]
    any_ = F.lit(False)
    for p, _ in framed:
        any_ = any_ | F.contains(line, F.lit(p))
    n = sum((F.regexp_count(line, F.lit(f"(?={re.escape(p)})")) for p, _ in framed), F.lit(0))
    at = lambda pos, part: F.length(part) - F.length(F.replace(part, F.lit(" "), F.lit("")))  # noqa: E731  blanks before
    firsts, lasts = [], []
    for p, _ in framed:
        has = F.contains(line, F.lit(p))
        firsts.append(F.when(has, at(None, F.substring_index(line, p, 1))))
        lasts.append(F.when(has, at(None, F.substring_index(line, p, -1))))
    total = F.length(line) - F.length(F.replace(line, F.lit(" "), F.lit("")))  # words + 1
    # Blanks after the last place, the phrase's own, and those before it add up to all.
    lasts = [total - v - (p.count(" ")) for v, (p, _) in zip(lasts, framed)]
    return {
        "n_base": F.when(any_, n).otherwise(0).cast("long"),
        "first_word": F.when(any_, F.least(*firsts)).cast("long"),
        "last_word": F.when(any_, F.greatest(*lasts)).cast("long"),
        "base_set": F.when(any_, F.array_compact(F.array(*[F.when(F.contains(line, F.lit(p)), F.lit(label)) for p, label in framed]))).otherwise(F.array().cast("array<string>")),
    }


def votes(rows: DataFrame, grams: DataFrame, near: int = NEAR, k: int = K) -> DataFrame:
    """rows(row, runs) -> row, label, score, start and end word, of verified spans."""
    hits = rows.select("row", F.posexplode("runs").alias("pos", "run")).join(F.broadcast(grams), "run")
    diagonal = hits.groupBy("row", "template", "label", "size", (F.col("pos") - F.col("at")).alias("diagonal")).agg(
        F.count(F.lit(1)).alias("votes"), F.min("pos").alias("lo"), F.max("pos").alias("hi"), F.bitmap_construct_agg(F.bitmap_bit_position(F.col("at") + 1)).alias("at")
    )
    by = Window.partitionBy("row", "template").orderBy("diagonal")
    fresh = F.coalesce((F.col("diagonal") - F.lag("diagonal").over(by) > near).cast("int"), F.lit(1))
    merged = diagonal.withColumn("fresh", fresh).withColumn("band", F.sum("fresh").over(by))
    # A template position counts once, however many of the merged diagonals hit it.
    span = merged.groupBy("row", "template", "label", "size", "band").agg(F.bitmap_count(F.bitmap_or_agg("at")).alias("places"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    cover = F.col("places") / F.col("size")
    dense = F.col("places") / (F.col("hi") - F.col("lo") + 1)
    ok = span.withColumn("score", cover).filter((cover >= MIN_COVER) & (dense >= MIN_DENSE))
    return ok.select("row", "label", "score", F.col("lo").alias("start"), (F.col("hi") + k).alias("end"))


def scan(docs: DataFrame, k: int = K) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, vote_score, spans. score: 1 where a phrase
    stands, else the votes' (the share of the best template that was found); vote_score: the votes' own."""
    spark = docs.sparkSession
    grams = templates(spark, k=k)
    known = F.array(*[F.lit(r["run"]) for r in grams.select("run").distinct().orderBy("run").collect()])
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    read = docs.select("doc_id", words_of(text).alias("w"))
    line = F.concat(F.lit(" "), F.array_join("w", " "), F.lit(" "))
    read = read.select("doc_id", F.size("w").cast("long").alias("n_words"), line.alias("line"), runs(F.col("w"), k).alias("runs"))
    read = read.withColumn("runs", F.when(F.arrays_overlap("runs", known), F.col("runs")))
    read = C.settle(read.select("doc_id", "n_words", *[v.alias(n) for n, v in base(F.col("line")).items()], "runs", F.monotonically_increasing_id().alias("row")), "license-rows")
    found = votes(read.filter("runs is not null").select("row", "runs"), grams, k=k)
    by_row = found.groupBy("row").agg(F.collect_set("label").alias("more"), F.max("score").alias("best"), F.array_sort(F.collect_list(F.struct("start", "end", "label"))).alias("spans"))
    out = read.drop("runs").join(by_row, "row", "left")
    every = F.array_sort(F.array_union("base_set", F.coalesce("more", F.array().cast("array<string>"))))
    return out.select(
        "doc_id", "n_words", "n_base", "first_word", "last_word",
        F.array_join(F.array_sort("base_set"), ",").alias("base_labels"), F.array_join(every, ",").alias("labels"),
        F.when(F.size("base_set") > 0, F.lit(1.0)).otherwise(F.coalesce("best", F.lit(0.0))).alias("score"),
        F.coalesce("best", F.lit(0.0)).alias("vote_score"), "spans",
    )
