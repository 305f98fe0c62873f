"""Licence scan by diagonal voting, with DataFrame functions alone.

All rolling word k-grams of the texts are joined by hash to their places in a fixed list of templates (broadcast: its
size is that of the list, not of the data). A hit votes for the diagonal "place in the text minus place in the template".
Votes are counted by diagonal, neighbouring diagonals (words put in or left out) are merged, and the span is verified:
each vote has compared its words, and enough of the template must be covered within a span of its length.
A row of its own per document goes through the same join, so that documents without a hit need no second pass.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.llm.common import ascii_lower

K = 3

#: Phrases whose every place counts, and their labels.
BASE_PHRASES = (("mit", "under the mit license"), ("apache-2", "apache license version 2"), ("cc-by-nc", "cc by nc"))

#: Wordings of public licences and their labels, found also when altered in places.
TEMPLATES = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction"),
    ("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software"),
    ("apache-2", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("gpl-3", "licensed under the gnu general public license version 3"),
    ("gpl", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("cc-by", "licensed under a creative commons attribution 4 0 international license"),
    ("cc-by-sa", "licensed under a creative commons attribution sharealike 4 0 international license"),
    ("cc-by-nc", "licensed under a creative commons attribution noncommercial 4 0 international license"),
)

NOT_A_WORD = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"


def template_grams(spark: SparkSession, base=BASE_PHRASES, templates=TEMPLATES) -> DataFrame:
    """One row per template and place, and row 0 that stands for every document."""
    rows = [(0, None, False, 0, 0, None, None, None)]
    for number, (label, phrase) in enumerate([*base, *templates], 1):
        words = phrase.split()
        if len(words) < K:
            raise ValueError(f"a phrase needs {K} words: {phrase}")
        rows += [(number, label, number <= len(base), len(words), i, *words[i : i + K]) for i in range(len(words) - K + 1)]
    made = spark.createDataFrame(rows, "template int, label string, base boolean, length int, place int, t1 string, t2 string, t3 string")
    return made.withColumn("t_hash", F.when(F.col("template") == 0, F.lit(0).cast("long")).otherwise(F.xxhash64("t1", "t2", "t3")))




def diagonal_votes(docs: DataFrame, grams: DataFrame, text_col: str = "text") -> DataFrame:
    """Hits of docs (which has _row) with the templates: _row, n_words, template..., diagonal and place; a row of template 0 for each document."""
    parts = docs.withColumn("_parts", F.split(ascii_lower(F.coalesce(F.col(text_col), F.lit(""))), NOT_A_WORD)).drop(text_col)
    lead = (F.element_at("_parts", 1) == "").cast("int")
    trail = ((F.size("_parts") > 1) & (F.element_at("_parts", -1) == "")).cast("int")
    words = parts.withColumn("n_words", F.size("_parts") - lead - trail)
    words = words.withColumn("_w", F.concat(F.array(F.lit(" ")), F.slice("_parts", lead + 1, F.col("n_words")))).drop("_parts")
    zipped = F.arrays_zip(F.col("_w").alias("a"), F.slice("_w", 2, F.size("_w")).alias("b"), F.slice("_w", 3, F.size("_w")).alias("c"))
    hits = words.select(*[c for c in words.columns if c != "_w"], F.posexplode(zipped).alias("_at", "_g"))
    hashed = hits.withColumn("_h", F.when(F.col("_at") == 0, F.lit(0).cast("long")).otherwise(F.xxhash64("_g.a", "_g.b", "_g.c")))
    document = (F.col("template") == 0) & (F.col("_at") == 0)
    same = (F.col("_g.a") == F.col("t1")) & (F.col("_g.b") == F.col("t2")) & (F.col("_g.c") == F.col("t3")) & (F.col("_at") > 0)
    joined = hashed.join(F.broadcast(grams), (F.col("_h") == F.col("t_hash")) & (document | same))
    return joined.withColumn("diagonal", F.col("_at") - 1 - F.col("place")).drop("_g", "_h", "_at", "t1", "t2", "t3", "t_hash")


def license_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slack: int = 3, least: float = 0.6) -> DataFrame:
    """Verified spans and a row with label null for each document: _row, id, n_words, label, base, first_word, end_word, coverage."""
    rows = docs.select(F.monotonically_increasing_id().alias("_row"), F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    votes = diagonal_votes(rows, template_grams(docs.sparkSession)).repartition("_row")
    keys = ["_row", "id", "n_words", "template", "label", "base", "length"]
    counted = votes.groupBy(*keys, "diagonal").agg(F.count("*").alias("votes"), F.min("place").alias("low"), F.max("place").alias("high"))
    along = Window.partitionBy("_row").orderBy("template", "diagonal")
    apart = (F.lag("template").over(along) != F.col("template")) | F.col("base") | (F.col("diagonal") - F.lag("diagonal").over(along) > slack)
    merged = counted.withColumn("_new", F.coalesce(apart, F.lit(True)).cast("int"))
    merged = merged.withColumn("_part", F.sum("_new").over(along.rowsBetween(Window.unboundedPreceding, 0)))
    spans = merged.groupBy(*keys, "_part").agg(
        F.min(F.col("diagonal") + F.col("low")).alias("first_word"),
        F.max(F.col("diagonal") + F.col("high") + K).alias("end_word"),
        F.sum("votes").alias("votes"),
    )
    spans = spans.withColumn("coverage", F.when(F.col("template") == 0, 0.0).otherwise(F.least(F.lit(1.0), F.col("votes") / (F.col("length") - K + 1))))
    whole = F.col("base") & (F.col("coverage") == 1.0)
    near = ~F.col("base") & (F.col("coverage") >= least) & (F.col("end_word") - F.col("first_word") <= F.col("length") + 2 * slack)
    return spans.where((F.col("template") == 0) | whole | near).drop("_part", "votes", "template", "length")


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slack: int = 3, least: float = 0.6) -> DataFrame:
    """One row per document: id, n_words, n_base, first_word, last_word, base_labels, labels, score (coverage of the best span).

    Null and empty texts have no words and no labels; rows with one id are judged each by itself. Base phrases never
    merge: n_base counts all their places, overlapping ones too.
    """
    spans = license_spans(docs, id_col, text_col, slack, least)
    base = F.coalesce("base", F.lit(False)) & F.col("label").isNotNull()
    join = lambda c: F.concat_ws(",", F.array_sort(F.collect_set(c)))  # noqa: E731  at most as many as there are labels
    out = spans.groupBy("_row", "id").agg(
        F.max("n_words").cast("long").alias("n_words"),
        F.count(F.when(base, 1)).alias("n_base"),
        F.min(F.when(base, F.col("first_word"))).cast("long").alias("first_word"),
        F.max(F.when(base, F.col("first_word"))).cast("long").alias("last_word"),
        join(F.when(base, F.col("label"))).alias("base_labels"),
        join("label").alias("labels"),
        F.max("coverage").alias("score"),
    )
    return out.drop("_row").withColumnRenamed("id", id_col)
