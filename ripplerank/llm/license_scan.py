"""License scanning: votes of rolling word k-grams on offset diagonals."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ascii_lower, words_of

#: Separators between words: ASCII other than digits and lower-case letters.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: Base phrases and their labels.
PHRASES = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))

#: Further notices the scanner knows, with labels of its own.
NOTICES = (
    ("licensed under cc by nc 4 0", "cc-by-nc"),
    ("this work is licensed under the gnu general public license version 3", "gpl-3-notice"),
    ("licensed under the apache license version 2 0", "apache-2-notice"),
    ("released under the mit license", "mit-notice"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software", "mit-grant"),
    ("redistribution and use in source and binary forms with or without modification are permitted", "bsd-grant"),
    ("this program is free software you can redistribute it and or modify it", "gpl-grant"),
)
#: Words that a fuzzy place may gain or lose in all: its diagonals lie this close together.
DRIFT = 6
#: Share of a notice's k-grams that a place must hold, in the notice's order.
COVERAGE = 0.7


def _templates(phrases: Sequence[tuple[str, str]], notices: Sequence[tuple[str, str]]) -> list[tuple]:
    """One row per template k-gram: k, gram, template, label, base, position, grams in the template."""
    rows = []
    for t, (text, label, base) in enumerate([*((p, x, True) for p, x in phrases), *((p, x, False) for p, x in notices)]):
        words = text.split()
        k = 2 if base else 3
        n = len(words) - k + 1
        if n < 1:
            raise ValueError(f"a template needs {k} words: {text!r}")
        rows += [(k, " ".join(words[i : i + k]), t, label, base, i, n) for i in range(n)]
    return rows


def scan_licenses(
    docs: DataFrame,
    phrases: Sequence[tuple[str, str]] = PHRASES,
    notices: Sequence[tuple[str, str]] = NOTICES,
    drift: int = DRIFT,
    coverage: float = COVERAGE,
) -> DataFrame:
    """License evidence of every whole text.

    Returns doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, notices.
    Each rolling 2-gram and 3-gram of a text that hashes to a template's k-gram votes, after
    a join on hash and words, for the diagonal text position - template position.
    A diagonal with all votes of a base phrase is a place of that phrase. For notices,
    the diagonals from each one on that lie within `drift` are merged into a place. A place is verified by its words: the
    template positions that its k-grams show in rising order, each counted once, are the share it holds, and it is kept
    where that reaches `coverage`. `score` is the best share (1 with any base phrase), and `notices` lists the best place of each
    notice that was kept as label:first word:end. Templates are a fixed
    list, so the joined table is broadcast. Null and empty texts give zero counts, null
    places, empty labels and score 0. Rows stay one to one, repeated rows included.
    """
    spark = docs.sparkSession
    grams = spark.createDataFrame(
        _templates(phrases, notices), "k int, gram string, template int, label string, base boolean, at int, grams int"
    )
    known = {k: [r[0] for r in grams.where(f"k = {k}").select(F.xxhash64("gram")).distinct().collect()] for k in (2, 3)}
    n, w = F.size("words"), F.col("words")

    def voters(k: int):
        def gram(i):
            return F.concat_ws(" ", *[F.get(w, i + j) for j in range(k)])

        if not known[k]:
            return F.array().cast("array<struct<k:int,pos:int,gram:string>>")
        spots = F.filter(F.sequence(F.lit(0), n - k), lambda i: F.xxhash64(gram(i)).isin(known[k]))
        spots = F.when(n >= k, spots).otherwise(F.array().cast("array<int>"))
        return F.transform(spots, lambda i: F.struct(F.lit(k).alias("k"), i.alias("pos"), gram(i).alias("gram")))

    rows = docs.select(
        "doc_id", F.monotonically_increasing_id().alias("row"), words_of(ascii_lower(F.col("text")), SEPARATORS).alias("words")
    ).select("doc_id", "row", n.cast("long").alias("n_words"), F.concat(voters(2), voters(3)).alias("votes"))
    hits = (
        rows.select("doc_id", "row", "n_words", F.inline_outer("votes"))
        .join(F.broadcast(grams), ["k", "gram"], "left")
        .groupBy("row", "doc_id", "n_words", "template", "label", "base", "grams", (F.col("pos") - F.col("at")).alias("diagonal"))
        .agg(F.collect_list("at").alias("ats"))
    )
    near_by = Window.partitionBy("row", "template").orderBy("diagonal").rangeBetween(0, drift)
    seen = F.transform("ats", lambda at: F.struct(at.alias("at"), (-F.col("diagonal") - at).alias("back")))
    placed = hits.withColumn("seen", F.when(~F.col("base"), seen)).withColumn("place", F.flatten(F.collect_list("seen").over(near_by)))
    # Longest run of rising template and text positions: least text position at which a run of each length may end.
    # Of one template position, later text positions come first, so that none follows another.
    run = F.aggregate(
        F.array_sort("place"), F.array().cast("array<int>"),
        lambda ends, x: F.concat(
            F.filter(ends, lambda e: e < -x["back"]), F.array(-x["back"]), F.slice(F.filter(ends, lambda e: e >= -x["back"]), F.lit(2), F.greatest(F.size(ends), F.lit(1)))
        ),
    )
    share = F.coalesce(F.size(run) / F.col("grams"), F.lit(0.0))
    texts = F.transform("place", lambda x: -x["back"])
    spots = placed.select(
        "row", "doc_id", "n_words", "label", "template", "diagonal", (F.col("base") & (F.size("ats") == F.col("grams"))).alias("exact"),
        F.when(~F.col("base"), share).alias("share"), F.array_min(texts).alias("begin"), (F.array_max(texts) + 3).alias("end"),
    )
    exact, near = F.col("exact"), F.col("share") >= coverage
    notice = F.when(near, F.struct("label", "template", (-F.col("share")).alias("least"), "begin", "end"))
    found = F.array_sort(F.collect_set(notice))
    first = F.filter(found, lambda x, i: (i == 0) | (F.get(found, i - 1)["template"] != x["template"]))
    return (
        spots.groupBy("row", "doc_id", "n_words")
        .agg(
            F.count(F.when(exact, 1)).alias("n_base"),
            F.min(F.when(exact, F.col("diagonal"))).cast("long").alias("first_word"),
            F.max(F.when(exact, F.col("diagonal"))).cast("long").alias("last_word"),
            F.array_join(F.array_sort(F.collect_set(F.when(exact, F.col("label")))), ",").alias("base_labels"),
            F.array_join(F.array_sort(F.collect_set(F.when(exact | near, F.col("label")))), ",").alias("labels"),
            F.coalesce(F.max(F.when(exact, F.lit(1.0)).otherwise(F.col("share"))), F.lit(0.0)).alias("score"),
            F.array_join(F.transform(first, lambda x: F.concat_ws(":", x["label"], x["begin"], x["end"])), ",").alias("notices"),
        )
        .drop("row")
    )
