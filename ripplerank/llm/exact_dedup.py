"""Exact duplicate removal by skew-safe combining."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, cut, neutral

#: Salts a digest group is dealt over before its winners meet.
SALTS = 16
#: A group of more rows than both is sent to its rows instead of joined to them: there are at most 1 / HOT_SHARE.
HOT_ROWS, HOT_SHARE = 100_000, 1e-4


def _keyed(docs: DataFrame) -> DataFrame:
    norm = ascii_lower(F.col("text"))
    return docs.select("doc_id", norm.alias("norm"), F.sha2(norm, 256).alias("text_sha256"), F.spark_partition_id().alias("at"))


def exact_groups(docs: DataFrame, salts: int = SALTS) -> DataFrame:
    """One row per distinct normalised text: text_sha256, keep_id, group_size, collided text or null.

    Three combining stages, each keyed by digest and by the full text: within
    a task (the partial aggregate), within a salt of the digest (tasks are dealt over the salts, so that a task
    hands on one row of each text), and globally. A hot group thus reaches the last stage as at most `salts` rows.
    """
    salted = (
        _keyed(docs)
        .groupBy("text_sha256", "norm", F.pmod(F.col("at"), F.lit(salts)).alias("salt"))
        .agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    )
    merged = (
        salted.repartition("text_sha256")
        .groupBy("text_sha256", "norm")
        .agg(F.max("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    )
    # Texts that share a digest without being equal keep their text as part of the key.
    return merged.groupBy("text_sha256").agg(
        F.count("*").alias("variants"),
        F.max("keep_id").alias("keep_id"),
        F.max("group_size").alias("group_size"),
        F.when(F.count("*") > 1, F.collect_list(F.struct("norm", "keep_id", "group_size"))).alias("texts"),
    )


def _decided(rows: DataFrame, groups: DataFrame, total: int) -> DataFrame:
    """`rows` (with doc_id, text_sha256) beside keep_id, group_size and kept of their group.

    Groups that hold more than a `HOT_SHARE` of all rows are at most 1 / HOT_SHARE; they are sent to the rows. The others are joined,
    where rows of a hot group take part under keys of their own, which meet nothing.
    """
    plain = groups.where("variants = 1 and group_size > 1").select("text_sha256", "keep_id", "group_size")
    limit = max(HOT_ROWS, int(total * HOT_SHARE))
    hot = plain.where(F.col("group_size") > limit).select(F.col("text_sha256"), F.struct("keep_id", "group_size").alias("hot"))
    warm = plain.where(F.col("group_size") <= limit).select(F.col("text_sha256").alias("key"), F.struct("keep_id", "group_size").alias("warm"))
    if not hot.isEmpty():
        rows = rows.join(F.broadcast(hot), "text_sha256", "left")
        rows = rows.withColumn("key", F.when(F.col("hot").isNull(), F.col("text_sha256")).otherwise(F.monotonically_increasing_id().cast("string")))
    else:
        rows = rows.withColumns({"hot": F.lit(None).cast(warm.schema["warm"].dataType), "key": F.col("text_sha256")})
    found = F.coalesce("hot", "warm")
    keep = F.when(found.isNull(), F.col("doc_id")).otherwise(found["keep_id"])
    return rows.join(warm, "key", "left").withColumns(
        {"keep_id": keep, "group_size": F.coalesce(found["group_size"], F.lit(1)).cast("long"), "kept": F.col("doc_id").eqNullSafe(keep)}
    ).drop("key", "hot", "warm")


def exact_dedup(docs: DataFrame, salts: int = SALTS, carry: bool = False) -> DataFrame:
    """Mark duplicates: doc_id, keep_id, group_size, kept, text_sha256 for every row of `docs`; with `carry`, beside all its columns.

    Texts are equal when identical after lower-casing A-Z; null counts as empty, so null
    and empty texts form one group. The largest doc_id of a group stays. Every row has a decision of its own: rows that
    repeat a doc_id with other texts belong to the groups of their texts, and repeated equal rows carry the same decision. A
    null doc_id never wins over a number; a group of null ids keeps them (keep_id null). An empty table gives an empty
    result. With `carry`, the columns of `docs` but doc_id are named by position, so that none can clash.
    """
    groups = cut(_groups_slim(docs, salts), "exact")
    total = docs.count()
    digest = F.sha2(ascii_lower(F.col("text")), 256).alias("text_sha256")
    named, names = neutral(docs, "doc_id", "text")
    extra = [c for c in names if c != "doc_id"] if carry else []
    columns = ["doc_id", "keep_id", "group_size", "kept", "text_sha256", *extra]
    out = _decided(named.select("doc_id", digest, *extra), groups, total).select(*columns)
    clashes = groups.where("variants > 1").select("text_sha256", F.inline("texts"))
    if clashes.isEmpty():
        return out
    norm = ascii_lower(F.col("text")).alias("norm")
    exact = named.select("doc_id", digest, norm, *extra).join(clashes, ["text_sha256", "norm"]).select(
        "doc_id", "keep_id", F.col("group_size").cast("long").alias("group_size"), F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256", *extra
    )
    return out.join(clashes.select("text_sha256").distinct(), "text_sha256", "left_anti").select(*columns).unionByName(exact)


def survivors(docs: DataFrame, salts: int = SALTS) -> DataFrame:
    """The rows of `docs` that stay, one for each text: of equal texts that of the largest doc_id, of rows equal in both the least by their other columns."""
    kept = exact_dedup(docs, salts, carry=True).where("kept")
    _, names = neutral(docs, "doc_id", "text")
    if not kept.groupBy("doc_id", "text_sha256").count().where("count > 1").isEmpty():
        # Rows that repeat a doc_id and a text; combined before their shuffle, so that many are harmless.
        ordered = not any(f.dataType.typeName() in ("map", "variant") for f in docs.schema.fields)
        row = (F.min if ordered else F.first)(F.struct(*names))
        kept = kept.groupBy("doc_id", "text_sha256").agg(row.alias("row")).select("row.*")
    return kept.select(*names).toDF(*docs.columns)


def _groups_slim(docs: DataFrame, salts: int) -> DataFrame:
    # Only groups that some later row must look up: several copies, or a shared digest.
    return exact_groups(docs, salts).where("variants > 1 or group_size > 1")
