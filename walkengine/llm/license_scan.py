"""License scan by diagonal voting, with DataFrame functions alone.

Templates are notices of known licenses as word sequences.  Every rolling word k-gram of a document is hashed and
joined to the template positions that have the hash; a hit at word i of the document and word j of a template votes
for the diagonal i - j.  Votes are summed per (document, template, diagonal), neighbouring diagonals (an inserted or
lost word) are merged, and a span counts if its verified k-grams cover enough of the template.  A k-gram counts only
when its words are equal, so hashes decide nothing alone.

The template table has a fixed, small size (``TEMPLATES``); its hashes are also pushed into the projection as a
literal set, so only document k-grams that hit leave the scan.  Phrases are templates whose places must be whole:
all their k-grams (k = 2) on one diagonal.

A null text counts as empty.  Documents without words or places get 0 counts, null positions, empty labels and
score 0.  Rows are scanned one by one: a null doc_id or one that other rows have (with any text) changes nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkengine.llm.common import let, only, read_table, staged, whole_text, words_of

#: Characters between words (after A-Z are lower-cased).
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Phrases that are labelled wherever they stand.
PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}
#: Short public notices, one or more of a label.
TEMPLATES = (
    ("mit", "Permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the Software to deal in the Software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the Software"),
    ("bsd", "Redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("apache", "Licensed under the Apache License Version 2 0 the License you may not use this file except in compliance with the License"),
    ("apache", "Licensed under the Apache License Version 2 0"),
    ("gpl", "This program is free software you can redistribute it and or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    ("gpl", "This work is licensed under the GNU General Public License version 3"),
    ("lgpl", "is free software you can redistribute it and or modify it under the terms of the GNU Lesser General Public License"),
    ("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License v 2 0"),
    ("cc-by-nc", "Licensed under CC BY NC 4 0"),
    ("cc-by-sa", "Licensed under CC BY SA 4 0"),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4 0 International License"),
    ("cc0", "To the extent possible under law the author has waived all copyright and related or neighboring rights to this work"),
    ("isc", "Permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("unlicense", "This is free and unencumbered software released into the public domain"),
    ("mit", "Released under the MIT License"),
)
#: Words in a k-gram of a phrase and of a template.
PHRASE_K, TEMPLATE_K = 2, 3
#: Diagonals this close are one alignment; share of a template's k-grams that a span must hold.
DRIFT, LEAST_SHARE = 3, 0.8


def lower_ascii(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def _gram(words: Column, i: Column, k: int) -> Column:
    return F.concat_ws(" ", *(words[i + j] for j in range(k)))


def template_positions(spark: SparkSession) -> DataFrame:
    """template, label, k, pos, n_grams, hash, gram: the join side, as large as the template table."""
    rows, number = [], 0
    for k, source in ((PHRASE_K, [(v, p) for p, v in PHRASES.items()]), (TEMPLATE_K, TEMPLATES)):
        for label, text in source:
            words = text.lower().split()
            grams = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)]
            rows += [(number, label, k, i, len(grams), g) for i, g in enumerate(grams)]
            number += 1
    table = spark.createDataFrame(rows, "template int, label string, k int, pos int, n_grams int, gram string")
    return table.withColumn("hash", F.xxhash64("k", "gram"))


def _hits(docs: DataFrame, table: DataFrame) -> DataFrame:
    """One row per document: n_words and the k-grams whose hash a template has."""
    known = [r.hash for r in table.select("hash").distinct().collect()]  # as many as the template table has

    def rolling(words: Column) -> Column:
        def of(k: int) -> Column:
            gram = lambda i: F.struct(i.alias("i"), F.lit(k).alias("k"), _gram(words, i, k).alias("gram"))
            return F.transform(F.sequence(F.lit(0), F.size(words) - k), gram)

        none = F.filter(F.array(F.struct(F.lit(0).alias("i"), F.lit(0).alias("k"), F.lit("").alias("gram"))), lambda x: F.lit(False))
        hit = lambda g: F.xxhash64(g["k"], g["gram"]).isin(known)
        parts = [F.when(F.size(words) >= k, F.filter(of(k), hit)).otherwise(none) for k in (PHRASE_K, TEMPLATE_K)]
        return F.struct(F.size(words).cast("long").alias("n_words"), F.concat(*parts).alias("hits"))

    words = words_of(lower_ascii(whole_text()), GAP)
    row = F.monotonically_increasing_id().alias("row")  # fixed by the staging that follows
    return only(docs, "doc_id", "text").select(row, "doc_id", let(words, rolling).alias("found")).select("row", "doc_id", "found.*")


def spans(docs: DataFrame, table: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(documents, places).  documents: row, doc_id, n_words; places: row, template, label, phrase, first, last, score."""
    table = template_positions(docs.sparkSession) if table is None else table
    found = staged(_hits(docs, table), "license-hits")  # a few k-grams of each text; read twice below
    gram = found.where(F.size("hits") > 0).select("row", F.explode("hits").alias("g")).select(
        "row", F.col("g.i").alias("i"), F.col("g.gram").alias("doc_gram"), F.xxhash64("g.k", "g.gram").alias("hash")
    )
    votes = (
        gram.join(F.broadcast(table), "hash")
        .where("doc_gram = gram")
        .groupBy("row", "template", "label", "k", "n_grams", (F.col("i") - F.col("pos")).alias("diagonal"))
        .agg(F.collect_set("pos").alias("held"), F.min("i").alias("first"), F.max("i").alias("last"))
    )
    phrases = votes.where((F.col("k") == PHRASE_K) & (F.size("held") == F.col("n_grams")))
    along = W.partitionBy("row", "template").orderBy("diagonal")
    merged = (
        votes.where(F.col("k") == TEMPLATE_K)
        .withColumn("gap", F.col("diagonal") - F.lag("diagonal").over(along))
        .withColumn("alignment", F.sum(F.when(F.col("gap") <= DRIFT, 0).otherwise(1)).over(along))
        .groupBy("row", "template", "label", "k", "n_grams", "alignment")
        .agg(
            F.array_distinct(F.flatten(F.collect_list("held"))).alias("held"),
            F.min("first").alias("first"),
            F.max("last").alias("last"),
        )
        .where(F.size("held") >= LEAST_SHARE * F.col("n_grams"))
    )
    columns = [F.col("row"), F.col("template"), F.col("label"), (F.col("k") == PHRASE_K).alias("phrase")]
    columns += [F.col("first").cast("long"), (F.col("last") + F.col("k") - 1).cast("long").alias("last")]
    columns += [(F.size("held") / F.col("n_grams")).alias("score")]
    return found.select("row", "doc_id", "n_words"), phrases.select(*columns).unionByName(merged.select(*columns))


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: n_words, n_base, first_word, last_word, base_labels, labels, score."""
    found, places = spans(docs)
    base = F.col("phrase")
    joined = lambda c: F.array_join(F.array_sort(F.collect_set(c)), ",")
    by_doc = places.groupBy("row").agg(
        F.count_if(base).alias("n_base"),
        F.min(F.when(base, F.col("first"))).alias("first_word"),
        F.max(F.when(base, F.col("first"))).alias("last_word"),
        joined(F.when(base, F.col("label"))).alias("base_labels"),
        joined("label").alias("labels"),
        F.max("score").alias("score"),
    )
    return found.join(by_doc, "row", "left").select(
        "doc_id",
        "n_words",
        F.coalesce("n_base", F.lit(0).cast("long")).alias("n_base"),
        "first_word",
        "last_word",
        F.coalesce("base_labels", F.lit("")).alias("base_labels"),
        F.coalesce("labels", F.lit("")).alias("labels"),
        F.coalesce("score", F.lit(0.0)).alias("score"),
    )


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(read_table(spark, sf_dir, "documents"))


QUERIES = {"op6_license_scan": op6_license_scan}
ORACLES: dict[str, str] = {}
