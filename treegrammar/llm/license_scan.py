"""License scans by diagonal voting, in DataFrame operations only.

Texts become words; every rolling three-word gram is hashed and joined to the gram positions of the license templates.
A hit votes for the diagonal document position minus template position. Votes are summed by diagonal, neighbouring
diagonals (a word added or lost moves the rest by one) are merged, and a merged span is verified: it must hold at least
``MIN_COVER`` of the template's grams, or all of them for a template of fewer than ``SHORT`` grams (one word tells such
licenses apart), within a stretch that is not much longer than the template. A phrase that stands
word for word is a single diagonal with every gram of its template.

The templates are a fixed list of a few hundred words, so their positions are broadcast. Texts are read once: each text
adds one sentinel gram that joins to a sentinel template, which keeps texts without any hit and their word counts.

Defined results: null texts count as empty and have no words; repeated rows give a row each; words of texts of any
length are all scanned; extra columns are ignored; an empty table gives no rows. Ties of the score need no order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

GRAM, MIN_COVER, SHORT, NEAR, SLACK = 3, 0.8, 12, 2, 1.5
SENTINEL = 0
#: The base phrases and their labels.
BASE = (("mit", "under the mit license"), ("apache-2", "apache license version 2"), ("cc-by-nc", "cc by nc"))
#: Templates of the method: opening words of well-known licenses and their usual notices.
MORE = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction"),
    ("apache-2", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license"),
    ("gpl-3", "licensed under the gnu general public license version 3"),
    ("gpl-2", "licensed under the gnu general public license version 2"),
    ("gpl", "redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("lgpl", "under the terms of the gnu lesser general public license"),
    ("agpl-3", "gnu affero general public license version 3"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("unlicense", "this is free and unencumbered software released into the public domain"),
    ("cc-by-sa", "cc by sa"),
    ("cc-by-nd", "cc by nd"),
    ("cc-by-nc", "creative commons attribution noncommercial"),
)


def word_line(text: Column) -> Column:
    """The words joined by single spaces. Letters beyond ASCII cannot stand in a template; a run of them keeps one letter."""
    plain = F.lower(F.regexp_replace(F.coalesce(text, F.lit("")), r"[^\x00-\x7F]+", "ÿ"))
    return F.trim(F.regexp_replace(plain, r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", " "))


def template_grams(spark, base=BASE, more=MORE) -> DataFrame:
    """gram, template, label, base, at, grams of every gram position of the templates, and the sentinel."""
    rows = []
    for number, (label, phrase) in enumerate([*base, *more], 1):
        w = phrase.split(" ")
        rows += [(*w[at : at + GRAM], number, label, number <= len(base), at, len(w) - GRAM + 1) for at in range(len(w) - GRAM + 1)]
    df = spark.createDataFrame(rows, "a string, b string, c string, template int, label string, base boolean, at int, grams int")
    df = df.select(F.xxhash64("a", "b", "c").alias("gram"), "template", "label", "base", "at", "grams")
    none = spark.range(1).select(F.lit(SENTINEL).cast("long").alias("gram"), F.lit(0).alias("template"), F.lit(None).cast("string").alias("label"), F.lit(False).alias("base"), F.lit(0).alias("at"), F.lit(1).alias("grams"))
    return df.union(none)


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score and spans of every row (doc_id, text)."""
    spark = docs.sparkSession
    line = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), word_line(F.col("text").cast("string")).alias("line"))
    words = line.select("row", "doc_id", F.when(F.col("line") == "", F.array().cast("array<string>")).otherwise(F.split("line", " ")).alias("w"))
    n = F.size("w")
    grams = F.when(n >= GRAM, F.transform(F.sequence(F.lit(0), n - GRAM), lambda i: F.xxhash64(F.col("w")[i], F.col("w")[i + 1], F.col("w")[i + 2]))).otherwise(F.array().cast("array<bigint>"))
    dealt = words.select("row", "doc_id", n.cast("long").alias("n_words"), F.posexplode(F.concat(grams, F.array(F.lit(SENTINEL).cast("long")))).alias("pos", "gram"))
    hits = dealt.join(F.broadcast(template_grams(spark)), "gram")  # a fixed list: at most a few hundred rows
    votes = hits.groupBy("row", "doc_id", "n_words", "template", "label", "base", "grams", (F.col("pos") - F.col("at")).alias("diagonal")).agg(
        F.count("*").alias("votes"), F.min("pos").alias("start"), F.max("pos").alias("end")
    )
    real = F.col("template") > 0
    # Diagonals of one template in one text, in order; a gap of more than NEAR starts a new span.
    by = Window.partitionBy("row", "template").orderBy("diagonal")
    apart = F.when(F.col("diagonal") - F.lag("diagonal").over(by) <= NEAR, 0).otherwise(1)
    spans = votes.withColumn("apart", apart).withColumn("span", F.sum("apart").over(by))
    spans = spans.groupBy("row", "doc_id", "n_words", "template", "label", "base", "grams", "span").agg(
        F.sum("votes").alias("votes"), F.min("start").alias("start"), (F.max("end") + GRAM - 1).alias("end"),
        F.sum((F.col("base") & (F.col("votes") == F.col("grams"))).cast("long")).alias("places"),
        F.min(F.when(F.col("base") & (F.col("votes") == F.col("grams")), F.col("diagonal"))).alias("first"),
        F.max(F.when(F.col("base") & (F.col("votes") == F.col("grams")), F.col("diagonal"))).alias("last"),
    )
    cover = F.least(F.lit(1.0), F.col("votes") / F.col("grams"))
    fits = F.col("end") - F.col("start") + 1 <= SLACK * (F.col("grams") + GRAM - 1) + NEAR
    found = real & ((F.col("places") > 0) | (cover >= F.when(F.col("grams") < SHORT, 1.0).otherwise(MIN_COVER)) & fits)
    joined = lambda c: F.concat_ws(",", F.array_sort(F.collect_set(c)))
    out = spans.groupBy("row", "doc_id", "n_words").agg(
        F.sum("places").cast("long").alias("n_base"), F.min("first").cast("long").alias("first_word"), F.max("last").cast("long").alias("last_word"),
        joined(F.when(F.col("places") > 0, F.col("label"))).alias("base_labels"), joined(F.when(found, F.col("label"))).alias("labels"),
        F.coalesce(F.max(F.when(found, F.when(F.col("places") > 0, F.lit(1.0)).otherwise(cover))), F.lit(0.0)).alias("score"),
    )
    return out.drop("row")
