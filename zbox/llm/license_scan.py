"""License scan by diagonal voting.

Licence texts and notices are templates: lists of words. The rolling word k-grams of every document
are joined (in Spark) to the places where the templates hold the same gram. A match at document
word i and template word j votes for the diagonal i - j; votes are added up per diagonal, diagonals
that lie next to each other (a word put in or left out) are merged, and each merged span is verified
by the share of the template's words that it covers.

Grams of three words (two for short phrases) are keyed by the 64-bit hash of their first two words
and must agree in the hash of all three as well. The template side is a constant of this module or the
caller's list, checked against ``MAX_TEMPLATE_WORDS`` before it is broadcast: it does not grow with
the documents. Document grams are made and probed within one stage; only votes are shuffled."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import free_name, lower_ascii

#: What stands between words, after lower-casing: ASCII that is neither digit nor small letter.
WORD_CHARS = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_WORD = re.compile(WORD_CHARS)
MAX_TEMPLATE_WORDS = 200_000


@dataclass(frozen=True)
class Template:
    name: str
    label: str
    text: str
    base: bool = False  # a phrase: counts only where every word stands


# The base phrases.
BASE_PHRASES = (
    Template("mit-phrase", "mit", "mit license", True),
    Template("apache-phrase", "apache", "apache license", True),
    Template("gpl-phrase", "gpl", "general public license", True),
)

# Public licence texts and notices (openings, or the part that tells them apart).
LICENSE_TEXTS = (
    Template("mit-notice", "mit", "released under the MIT License"),
    Template("mit-grant", "mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions"),
    Template("mit-warranty", "mit", "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT"),
    Template("apache-notice", "apache", "licensed under the Apache License, Version 2.0"),
    Template("apache-header", "apache", "you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    Template("apache-warranty", "apache", "distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied"),
    Template("gpl-notice", "gpl", "licensed under the GNU General Public License"),
    Template("gpl-header", "gpl", "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    Template("lgpl-notice", "lgpl", "under the terms of the GNU Lesser General Public License"),
    Template("agpl-notice", "agpl", "under the terms of the GNU Affero General Public License"),
    Template("bsd-grant", "bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    Template("bsd-notice", "bsd", "licensed under the BSD License"),
    Template("isc-grant", "isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies"),
    Template("mpl-notice", "mpl", "This Source Code Form is subject to the terms of the Mozilla Public License"),
    Template("epl-notice", "epl", "made available under the terms of the Eclipse Public License"),
    Template("unlicense", "unlicense", "This is free and unencumbered software released into the public domain"),
    Template("cc-by-nc", "cc-by-nc", "licensed under CC BY-NC 4.0"),
    Template("cc-by-sa", "cc-by-sa", "licensed under CC BY-SA 4.0"),
    Template("cc-by", "cc-by", "licensed under CC BY 4.0"),
    Template("cc-long", "cc", "licensed under a Creative Commons Attribution"),
    Template("cc0", "cc0", "dedicated to the public domain under CC0"),
)


def template_words(text: str) -> list[str]:
    return _WORD.findall(text.translate({c: c + 32 for c in range(65, 91)}))


def _template_index(spark: SparkSession, templates: tuple[Template, ...]) -> DataFrame:
    rows, total = [], 0
    for t in templates:
        w = template_words(t.text)
        if len(w) < 2:
            raise ValueError(f"template {t.name} has fewer than two words")
        total += len(w)
        k = 2 if t.base or len(w) < 4 else 3
        rows += [(t.name, t.label, t.base, len(w), j, k, w[j], w[j + 1], w[j + 2] if k == 3 else "") for j in range(len(w) - k + 1)]
    if total > MAX_TEMPLATE_WORDS:
        raise ValueError(f"templates have {total} words, more than {MAX_TEMPLATE_WORDS}: too many to broadcast")
    schema = "template string, label string, base boolean, len int, tpos int, k int, w1 string, w2 string, w3 string"
    rows.append((None,) * 9)  # the place that stands for a document itself
    gram = F.when(F.col("template").isNull(), 0).otherwise(F.xxhash64("w1", "w2"))
    whole = F.when(F.col("k") == 3, F.xxhash64("w1", "w2", "w3"))
    return spark.createDataFrame(rows, schema).select("template", "label", "base", "len", "tpos", "k", gram.cast("bigint").alias("gram"), whole.alias("whole"))


def scan(docs: DataFrame, id_col: str = "doc_id", text: str = "text", templates: tuple[Template, ...] = BASE_PHRASES + LICENSE_TEXTS, min_coverage: float = 0.8, max_shift: int = 3) -> DataFrame:
    """One row per row of ``docs``: id_col, n_words, n_base, first_word, last_word, base_labels,
    labels, score, spans.

    n_base, first_word and last_word are about the base phrases; labels adds the templates whose
    verified coverage is at least ``min_coverage``; score is the best coverage (0 to 1); spans lists
    the verified ones (template, label, first_word, last_word, coverage), by place and name.

    Null text: no words, no labels, score 0. Empty text: the same. Null ids are carried. Repeated rows
    give equal repeated rows. Other columns are not read, so their names cannot clash. An empty table
    gives an empty result."""
    spark = docs.sparkSession
    index = F.broadcast(_template_index(spark, templates))
    df = docs.select(F.col(f"`{id_col}`").alias("id"), lower_ascii(F.col(text)).alias("t"))
    df = df.select("id", F.xxhash64("t").alias("h"), F.regexp_extract_all("t", F.lit(WORD_CHARS), F.lit(0)).alias("w"))
    at = lambda i: F.get(F.col("w"), i)
    n = F.size("w")
    gram = lambda i: F.struct(F.xxhash64(at(i), at(i + 1)).alias("gram"), F.xxhash64(at(i), at(i + 1), at(i + 2)).alias("triple"))
    none = F.array().cast("array<struct<gram:bigint,triple:bigint>>")
    grams = F.when(n < 2, none).otherwise(F.transform(F.sequence(F.lit(0), n - 2), gram))
    first = F.struct(F.lit(0).cast("bigint").alias("gram"), F.lit(0).cast("bigint").alias("triple"))  # stands for the document itself
    df = df.select("id", "h", F.size("w").alias("n"), F.concat(F.array(first), grams).alias("g"))
    # outer: an inner explode would have the optimizer test the array's size beneath, making it again for every place
    df = df.select("id", "h", "n", F.posexplode_outer("g").alias("p", "e")).select("id", "h", "n", "p", F.col("e.gram").alias("gram"), F.col("e.triple").alias("triple"))
    head = F.col("template").isNull() & (F.col("p") == 0)
    same = F.col("template").isNotNull() & (F.col("p") > 0) & (F.col("whole").isNull() | (F.col("triple") == F.col("whole")))
    votes = df.join(index, "gram").filter(head | same)
    i = F.when(~head, F.col("p") - 1)
    votes = votes.select("id", "h", "template", "label", "base", "len", "k", "tpos", i.alias("i"), F.when(head, F.col("n")).alias("n_words"))
    # one shuffle: everything below is keyed by (id, h) first
    votes = votes.repartition("id", "h")
    diagonals = votes.groupBy("id", "h", "template", "label", "base", "len", "k", (F.col("i") - F.col("tpos")).alias("diagonal")).agg(
        F.collect_set("tpos").alias("tpos"), F.min("i").alias("first"), F.max("i").alias("last"), F.max("n_words").alias("n_words"), F.count("*").alias("m")
    )
    by = Window.partitionBy("id", "h", "template").orderBy("diagonal")
    before = F.lag("diagonal").over(by)
    apart = (F.col("base") | before.isNull() | (F.col("diagonal") - before > max_shift)).cast("int")
    diagonals = diagonals.withColumn("apart", apart).withColumn("cluster", F.sum("apart").over(by))
    merged = diagonals.groupBy("id", "h", "template", "label", "base", "len", "k", "cluster").agg(
        F.flatten(F.collect_list("tpos")).alias("tpos"), F.min("first").alias("first"), F.max("last").alias("last"), F.max("n_words").alias("n_words"), F.max("m").alias("m")
    )
    covered = F.size(F.array_distinct(F.flatten(F.transform("tpos", lambda j: F.sequence(j, j + F.col("k") - 1)))))
    coverage = F.when(F.col("template").isNotNull(), covered / F.col("len"))
    merged = merged.withColumn("coverage", F.least(coverage, F.lit(1.0)))
    base = F.col("base") & (F.col("coverage") >= 1.0)
    other = ~F.col("base") & (F.col("coverage") >= min_coverage)
    span = F.struct((F.col("first")).alias("first_word"), (F.col("last") + F.col("k") - 1).alias("last_word"), "template", "label", "coverage")
    out = merged.groupBy("id", "h").agg(
        F.max("n_words").cast("long").alias("n_words"),
        F.count_if(base).alias("n_base"),
        F.min(F.when(base, F.col("first"))).cast("long").alias("first_word"),
        F.max(F.when(base, F.col("first"))).cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.collect_set(F.when(base, F.col("label")))), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.collect_set(F.when(base | other, F.col("label")))), ",").alias("labels"),
        F.coalesce(F.max(F.when(base | ~F.col("base"), F.col("coverage"))), F.lit(0.0)).alias("score"),
        F.array_sort(F.collect_list(F.when(base | other, span))).alias("spans"),
        F.max(F.when(F.col("template").isNull(), F.col("m"))).alias("copies"),
    )
    each = free_name(out, "each")
    out = out.withColumn(each, F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return out.select(F.col("id").alias(id_col), "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans")


def spans_schema() -> T.ArrayType:
    return T.ArrayType(T.StructType([T.StructField("first_word", T.IntegerType()), T.StructField("last_word", T.IntegerType()), T.StructField("template", T.StringType()), T.StructField("label", T.StringType()), T.StructField("coverage", T.DoubleType())]))
