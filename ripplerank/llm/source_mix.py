"""Mixing sources to target weights by systematic sampling, in DataFrame expressions only."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ASCII_SPACE, cut, neutral, words_of

SEED = 20177
#: Hash buckets that documents of one source and one size are dealt over.
BUCKETS = 256


def source_targets(sizes: DataFrame, weights: Sequence[float], share: float, cap: float) -> DataFrame:
    """Words each source should give: skey, source_size, target.

    `sizes` has (skey, source_size). Weights repeat over the sources in order of skey.
    Capped sources give `cap` times their size; the others share the rest by weight. With
    sources sorted by the level at which they reach their cap, the common level
    follows from running sums, so no loop is needed.
    """
    by_key = Window.orderBy("skey")
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.row_number().over(by_key) - 1, F.lit(len(weights))) + 1).cast("int"))
    s = sizes.withColumn("weight", w)
    by_level = Window.orderBy("level", "skey")
    before, every = by_level.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    s = s.withColumn("level", F.col("source_size") * F.lit(float(cap)) / F.col("weight"))
    s = s.select(
        "*",
        F.coalesce(F.sum("source_size").over(before), F.lit(0)).alias("done"),
        F.coalesce(F.sum("weight").over(before), F.lit(0.0)).alias("used"),
        F.sum("source_size").over(every).alias("total"),
        F.sum("weight").over(every).alias("all_weight"),
    )
    # The level if exactly the sources before this one were capped.
    s = s.withColumn("try", (F.lit(float(share)) * F.col("total") - F.lit(float(cap)) * F.col("done")) / (F.col("all_weight") - F.col("used")))
    fits = F.min(F.when(F.col("try") <= F.col("level"), F.struct("level", "skey", "try"))).over(every)
    level = F.coalesce(fits["try"], F.max("level").over(every))
    return s.select(
        "skey", "source_size",
        F.least(F.col("source_size") * F.lit(float(cap)), level * F.col("weight")).alias("target"),
    )


def _sized(docs: DataFrame) -> DataFrame:
    """Adds skey, size and bucket to rows that have doc_id, text and source."""
    named = F.coalesce(F.col("doc_id").cast("string"), "text", F.lit(""))
    return docs.withColumns({
        "skey": F.when(F.col("source").isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), F.col("source"))),
        "size": F.size(words_of(F.coalesce("text", F.lit("")), ASCII_SPACE)).cast("long"),
        "bucket": F.conv(F.substring(F.md5(named), 1, 2), 16, 10).cast("int"),
    })


def _starts(sized: DataFrame, weights: Sequence[float], share: float, cap: float, seed: int) -> DataFrame:
    """Where the documents of each (skey, size, bucket) begin in their source's order, with the source's target, rate and shift."""
    cells = cut(sized.groupBy("skey", "size", "bucket").agg(F.count("*").alias("n")), "cells")
    totals = cells.groupBy("skey").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    unit = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.col("skey"))), 1, 5), 16, 10).cast("double") / F.lit(float(16**5))
    per_source = source_targets(totals, weights, share, cap).withColumn("shift", unit).withColumn(
        "rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    )
    by_size = Window.partitionBy("skey").orderBy("size").rowsBetween(Window.unboundedPreceding, -1)
    bases = (
        cells.groupBy("skey", "size").agg(F.sum("n").alias("n"))
        .select("skey", "size", F.coalesce(F.sum("n").over(by_size), F.lit(0)).alias("base"))
        .join(per_source, "skey")
    )
    by_bucket = Window.partitionBy("skey", "size").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    return cells.select("skey", "size", "bucket", F.coalesce(F.sum("n").over(by_bucket), F.lit(0)).alias("within")).join(bases, ["skey", "size"])


def _drawn(sized: DataFrame, starts: DataFrame, *ties: str) -> DataFrame:
    """Adds the copies that the mix takes of each row."""
    in_cell = Window.partitionBy("skey", "size", "bucket").orderBy("doc_id", *ties)
    placed = sized.withColumn("row", F.row_number().over(in_cell)).join(starts, ["skey", "size", "bucket"])
    rank = F.col("base") + F.col("within") + F.col("row")
    crossed = F.floor(F.col("shift") + F.col("rate") * rank) - F.floor(F.col("shift") + F.col("rate") * (rank - 1))
    return placed.withColumn("copies", F.least(crossed, F.ceil("rate")).cast("long"))


def mix_sources(
    docs: DataFrame, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, seed: int = SEED
) -> DataFrame:
    """Copies of each document for the mix: doc_id, source, size, source_size, target, copies, taken.

    Each document of a source expects target / source_size copies. Documents of
    a source are ordered by size, then by a hash bucket, then by doc_id; with the running
    expectation shifted by one random offset per source (a digest of seed and source, so
    reruns agree), a document is emitted once for each integer it crosses. Sorting by
    size keeps the words taken within about one document of the target. The
    running position is found in levels (sizes, buckets, rows), so that no task sees
    a whole source; what is known of each source, a row a source, is ordered in one task. Null or blank texts have size 0 and take
    nothing; sources without words have target 0; null is a source of its own. Rows that repeat a doc_id
    are sampled one by one. An empty table gives an empty result; other columns are ignored.
    """
    sized = cut(_sized(docs.select("doc_id", "source", "text")).drop("text"), "sized")
    drawn = _drawn(sized, _starts(sized, weights, share, cap, seed))
    return drawn.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def emit_mix(docs: DataFrame, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, seed: int = SEED) -> DataFrame:
    """The mixed corpus: the rows of `docs`, each as often as the mix takes it.

    Every row carries its own decision, so repeated and null doc_ids are drawn one by one (equal ids by text), and no
    decision is joined back. Columns are those of `docs`, whatever their names.
    """
    rows, names = neutral(docs, "doc_id", "text", "source")
    sized = cut(_sized(rows.select("doc_id", "source", "text")).drop("text"), "sized")
    drawn = _drawn(_sized(rows), _starts(sized, weights, share, cap, seed), "text")
    copy = F.explode(F.when(F.col("copies") > 0, F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return drawn.select(*names, copy.alias("copy")).select(*names).toDF(*docs.columns)
