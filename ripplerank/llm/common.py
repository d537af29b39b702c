"""What the corpus operators share: table access, lineage cuts, distributed components."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.lineage import cut, shared_path  # noqa: F401  for the operators

#: ASCII white space as the contracts define it, for Java's and Python's regular expressions.
ASCII_SPACE = r"[\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark alone so that any Hadoop path works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only; null counts as empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def words_of(text: Column, separators: str) -> Column:
    """Non-empty pieces between runs of `separators`."""
    return F.filter(F.split(text, separators), lambda w: w != "")


def free_name(df: DataFrame, base: str) -> str:
    """A column name that `df` does not have."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base += "_"
    return base


def neutral(df: DataFrame, *kept: str) -> tuple[DataFrame, list[str]]:
    """`df` with all columns but `kept` named by position, so that none clashes with an operator's, and those names."""
    names = [c if c in kept else f"__column{i}" for i, c in enumerate(df.columns)]
    return df.toDF(*names), names


def components(edges: DataFrame, label: str = "cc", max_rounds: int = 60) -> DataFrame:
    """Connected components of undirected edges (a, b): rows (node, component), component = least node.

    Alternates the small-star and large-star rewrites: every vertex ties its smaller
    neighbours, then its larger ones, to the least vertex it knows. Both are a
    min-aggregate (combined before its shuffle, so hubs are harmless) and an equi-join that
    adaptive execution may split. The small star goes first, as it leaves one edge for each
    vertex beside those between hubs. Loops and null ends are ignored; no edges give no
    rows. Only a flag reaches the driver each round.
    """
    e = cut(
        edges.where(F.col("a").isNotNull() & F.col("b").isNotNull() & (F.col("a") != F.col("b")))
        .select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        .distinct(),
        label,
    )
    for _ in range(max_rounds):
        if _stars(e):
            break
        low = e.groupBy("a").agg(F.min("b").alias("m"))
        small = e.join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.withColumnRenamed("m", "b")).distinct()
        e = cut(small, label)
        if _stars(e):
            break
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        e = cut(large, label)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    stars = e.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return stars.unionByName(stars.select(F.col("component").alias("node"), "component").distinct())


def _stars(e: DataFrame) -> bool:
    """Whether every vertex has one smaller neighbour or none, and centres have none: components are read off."""
    if not e.groupBy("a").count().where("count > 1").isEmpty():
        return False
    return e.join(e.select(F.col("b").alias("a")).distinct(), "a", "left_semi").isEmpty()
