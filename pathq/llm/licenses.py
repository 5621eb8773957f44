"""License scans by diagonal voting, in DataFrame operations only.

Every rolling word pair of every document is hashed and joined with the positions of the same pairs in a
small fixed table of templates (license phrases and sentences). A match at document word ``p`` and template
word ``t`` votes for the diagonal ``p - t``. Votes are counted per document, template and diagonal;
neighbouring diagonals are merged, which bridges inserted or missing words; a merged span counts if it
covers enough of its template.

Edge cases: a null or empty text has no words, no places and null first and last word. Repeated rows each
get their own result row. A null ``doc_id`` is an id like any other. Extra columns are ignored. Very long
texts are read whole; one text's words are held in one task.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathq.llm.common import Workspace, ascii_lower

WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
GRAM = 2


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    base: bool = False


# Phrases of the contract, and sentences of widely used public licenses.
BASE = (
    Template("cc-by", "cc by", True),
    Template("gpl", "general public license", True),
    Template("reserved", "all rights reserved", True),
)
LICENSES = (
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    Template("apache-2.0", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    Template("gpl-notice", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    Template("lgpl", "gnu lesser general public license"),
    Template("agpl", "gnu affero general public license"),
    Template("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    Template("unlicense", "this is free and unencumbered software released into the public domain"),
    Template("cc-by-sa", "creative commons attribution sharealike"),
    Template("cc-by-nc", "creative commons attribution noncommercial"),
    Template("cc0", "no rights reserved"),
    Template("public-domain", "dedicated to the public domain"),
)


def gram_hash(words: list[Column]) -> Column:
    return F.xxhash64(*words)


def template_positions(spark: SparkSession, templates: tuple[Template, ...]) -> DataFrame:
    """One row per template and word pair: (gram, tid, t, label, base, n_grams). Its size is that of the fixed table above."""
    rows = []
    for tid, template in enumerate(templates):
        words = template.text.split()
        rows += [(tid, t, *words[t : t + GRAM], template.label, template.base, len(words) - GRAM + 1) for t in range(len(words) - GRAM + 1)]
    df = spark.createDataFrame(rows, f"tid int, t int, {', '.join(f'w{i} string' for i in range(GRAM))}, label string, base boolean, n_grams int")
    return df.select(gram_hash([F.col(f"w{i}") for i in range(GRAM)]).alias("gram"), "tid", "t", "label", "base", "n_grams")


def document_words(docs: DataFrame) -> DataFrame:
    """(doc_id, th, words): th is a hash of the text, which together with doc_id names a document."""
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.regexp_extract_all(ascii_lower(text), F.lit(WORD), F.lit(0))
    return docs.select(F.col("doc_id"), F.xxhash64(text, F.length(text)).alias("th"), words.alias("words"))


def matches(spark: SparkSession, worded: DataFrame, templates: tuple[Template, ...]) -> DataFrame:
    """(doc_id, th, n_words, tid, label, base, n_grams, p, t): matching pairs of word positions, and a row with tid -1 per document.

    That row comes from a marker put before the document's pairs, so that texts are read and cut into words once.
    """
    marker = F.xxhash64(F.lit("a document"), F.lit(-1))
    pairs = F.transform("words", lambda w, i: gram_hash([w, F.get(F.col("words"), i + 1)]))
    grams = worded.select("doc_id", "th", F.size("words").alias("n_words"), F.posexplode(F.concat(F.array(marker), pairs)).alias("p", "gram"))
    known = template_positions(spark, templates)
    marked = known.unionByName(spark.range(1).select(marker.alias("gram"), F.lit(-1).alias("tid"), F.lit(0).alias("t"), F.lit("").alias("label"), F.lit(False).alias("base"), F.lit(0).alias("n_grams")))
    hits = grams.join(F.broadcast(marked), "gram")
    return hits.select("doc_id", "th", F.col("n_words").cast("long").alias("n_words"), "tid", "label", "base", "n_grams", (F.col("p") - 1).cast("long").alias("p"), "t")


def votes(matched: DataFrame) -> DataFrame:
    """(doc_id, th, tid, label, base, n_grams, diagonal, p, t). A row of documents may be there twice; its matches count once."""
    return matched.filter("tid >= 0").select("doc_id", "th", "tid", "label", "base", "n_grams", "p", (F.col("p") - F.col("t")).alias("diagonal"), "t").distinct()


def spans(voted: DataFrame, max_shift: int = 2, min_cover: float = 0.8) -> DataFrame:
    """Verified spans: (doc_id, th, tid, label, base, n_grams, start, end, n_votes, cover).

    Base phrases need every vote on one diagonal. For the other templates, diagonals that lie at most
    ``max_shift`` apart and whose matches overlap or follow each other within the template's length form one
    span, which needs ``min_cover`` of the template's distinct word pairs.
    """
    key = ["doc_id", "th", "tid", "label", "base", "n_grams"]
    diagonals = voted.groupBy(*key, "diagonal").agg(
        F.count(F.lit(1)).alias("n"), F.min("p").alias("first"), F.max("p").alias("last"), F.collect_set("t").alias("ts")
    )
    exact = diagonals.filter("base").filter("n = n_grams").select(*key, F.col("first").alias("start"), (F.col("last") + GRAM).alias("end"), F.col("n").alias("n_votes"), F.lit(1.0).alias("cover"))
    order = Window.partitionBy("doc_id", "th", "tid").orderBy("diagonal", "first")
    apart = (F.col("diagonal") - F.lag("diagonal").over(order) > max_shift) | (F.col("first") > F.lag("last").over(order) + F.col("n_grams"))
    merged = (
        diagonals.filter(~F.col("base"))
        .withColumn("opens", F.coalesce(apart, F.lit(True)).cast("int"))
        .withColumn("span", F.sum("opens").over(order))
        .groupBy(*key, "span")
        .agg(F.min("first").alias("start"), (F.max("last") + GRAM).alias("end"), F.sum("n").alias("n_votes"), F.size(F.array_distinct(F.flatten(F.collect_list("ts")))).alias("covered"))
        .withColumn("cover", F.col("covered") / F.col("n_grams"))
        .filter(F.col("cover") >= min_cover)
    )
    return exact.unionByName(merged.select(*exact.columns))


def scan(spark: SparkSession, docs: DataFrame, templates: tuple[Template, ...] = BASE + LICENSES, max_shift: int = 2, min_cover: float = 0.8) -> DataFrame:
    """Per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, n_spans.

    ``score`` is the share of evidence found: 1 for a verified license sentence or two or more base places,
    0.5 for a single base place, else 0.
    """
    matched = Workspace(spark, "licenses").table(matches(spark, document_words(docs), templates), "matches")
    found = spans(votes(matched), max_shift, min_cover)
    joined = lambda c: F.concat_ws(",", F.array_sort(F.collect_set(c)))
    base = F.when(F.col("base"), F.col("start"))
    per_doc = found.groupBy(F.col("doc_id").alias("d"), F.col("th").alias("h")).agg(
        F.count(base).alias("n_base"),
        F.min(base).alias("first_word"),
        F.max(base).alias("last_word"),
        joined(F.when(F.col("base"), F.col("label"))).alias("base_labels"),
        joined("label").alias("labels"),
        F.count(F.lit(1)).alias("n_spans"),
        F.max(F.when(~F.col("base"), F.col("cover")).otherwise(0.0)).alias("best"),
    )
    counted = matched.filter("tid = -1").select("doc_id", "th", "n_words")
    zero, none = F.lit(0).cast("long"), F.lit("")
    strength = F.least(F.lit(1.0), F.greatest(F.coalesce("best", F.lit(0.0)), F.coalesce("n_base", zero) * 0.5))
    return counted.join(per_doc, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("h")), "left").select(
        "doc_id",
        "n_words",
        F.coalesce("n_base", zero).alias("n_base"),
        "first_word",
        "last_word",
        F.coalesce("base_labels", none).alias("base_labels"),
        F.coalesce("labels", none).alias("labels"),
        strength.cast("double").alias("score"),
        F.coalesce("n_spans", zero).alias("n_spans"),
    )
