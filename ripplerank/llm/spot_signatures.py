"""Document fingerprints from chains of content words behind common-word anchors, in DataFrame expressions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, words_of

SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Most common words taken as anchors, by number of documents that hold them.
ANCHORS = 128
#: Content words in a chain.
CHAIN = 3
#: Documents that one ordered bucket should hold.
BUCKET_ROWS = 2000
_FIRST = -(1 << 63)


def _words(text: Column) -> Column:
    return words_of(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS)


def common_words(docs: DataFrame, most: int = ANCHORS) -> list[str]:
    """The words found in the most documents of the whole table, ties by word; at most `most` reach the driver."""
    counts = docs.select(F.explode(F.array_distinct(_words(F.col("text")))).alias("w")).groupBy("w").count()
    return [r[0] for r in counts.orderBy(F.desc("count"), "w").limit(most).collect()]


def with_signatures(df: DataFrame, text: str, out: str, anchors: list[str], chain: int = CHAIN) -> DataFrame:
    """Add `out`: the sorted distinct signatures (32-bit) of column `text`.

    Each anchor signs with itself and the next `chain` content words, anchors between them
    skipped. The opening words sign too, so only a text without words has no signature.
    Null counts as empty.
    """
    def anchor(w: Column) -> Column:
        return w.isin(anchors) if anchors else F.lit(False)

    df = df.withColumn("__w", _words(F.col(text)))
    df = df.withColumns({
        "__c": F.filter("__w", lambda w: ~anchor(w)),
        "__a": F.filter(F.transform("__w", lambda w, i: F.when(anchor(w), F.struct(w.alias("w"), i.alias("i")))), lambda s: s.isNotNull()),
    })
    # The j-th anchor at word i has i - j content words before it.
    signed = F.transform(
        F.filter(F.transform("__a", lambda s, j: F.struct(s["w"].alias("w"), (s["i"] - j).alias("p"))), lambda s: s["p"] + chain <= F.size("__c")),
        lambda s: F.hash(s["w"], *[F.get(F.col("__c"), s["p"] + d) for d in range(chain)]),
    )
    opening = F.when(F.size("__w") > 0, F.array(F.hash(F.lit("^"), *[F.get(F.col("__w"), F.lit(d)) for d in range(chain)]))).otherwise(F.array().cast("array<int>"))
    return df.withColumn(out, F.array_sort(F.array_distinct(F.concat(opening, signed)))).drop("__w", "__c", "__a")


def likeness(a: str, b: str, floor: float = 0.0) -> Column:
    """Jaccard likeness of two signature columns; 0 where the lengths alone keep it under `floor`. Two empty sets are alike."""
    x, y = F.size(a).cast("double"), F.size(b).cast("double")
    both = F.size(F.array_intersect(a, b)).cast("double")
    return (
        F.when((x == 0) & (y == 0), F.lit(1.0))
        .when((x == 0) | (y == 0) | (F.least(x, y) < floor * F.greatest(x, y)), F.lit(0.0))
        .otherwise(both / (x + y - both))
    )


def length_part(size: Column, threshold: float) -> Column:
    """Partition of a set length: sets at or above `threshold` in likeness lie in the same or in neighbouring partitions."""
    return F.floor(F.log(F.greatest(size, F.lit(1)).cast("double")) / F.lit(-math.log(threshold)) + 1e-9).cast("int")


def fingerprint(signatures: str) -> Column:
    """Signatures as text: eight hex digits each, in order."""
    return F.array_join(F.transform(signatures, lambda s: F.lpad(F.lower(F.hex(F.pmod(s.cast("long"), F.lit(1 << 32)))), 8, "0")), "")


def _prefixes(classes: DataFrame, threshold: float) -> DataFrame:
    """id, n, part and s for the signatures that a set must share one of with any other at or above the threshold: its rarest.

    Signatures are ordered by the number of sets that hold them, so that a common one is met only by sets with little else.
    """
    every = classes.select("id", F.size("sigs").alias("n"), F.explode("sigs").alias("s"))
    common = every.groupBy("s").agg(F.count("*").alias("held")).where(F.col("held") > 1)
    # What a single set holds meets nothing; such signatures come first of all and need no join.
    ranked = every.join(common, "s").groupBy("id", "n").agg(F.array_sort(F.collect_list(F.struct("held", "s"))).alias("shared"))
    kept = (F.col("n") - F.ceil(F.lit(threshold) * F.col("n")) + 1).cast("int") - (F.col("n") - F.size("shared"))
    return ranked.where(kept > 0).select("id", "n", length_part(F.col("n"), threshold).alias("part"), F.explode(F.transform(F.slice("shared", F.lit(1), kept), lambda x: x["s"])).alias("s"))


def similar_pairs(signed: DataFrame, threshold: float = 0.8) -> DataFrame:
    """Pairs (id_a, id_b, likeness) of different fingerprints at or above `threshold`, plus (rep, member) rows for equal ones.

    `signed` has (doc_id, sigs). Equal sets are collapsed to their least doc_id first and come
    back as pairs with likeness 1 to it, so a group of n copies costs n rows. The others
    are dealt by length partition, meet on the signatures of their prefix (any two
    sets above the threshold share one), drop out by length, and are then compared whole.
    Sets without signatures match nothing. Null ids are left out.
    """
    rows = signed.where("doc_id is not null and size(sigs) > 0")
    classes = cut(rows.groupBy("sigs").agg(F.min("doc_id").alias("id")), "spots")
    copies = rows.join(classes, "sigs").where("doc_id <> id").select(F.col("id").alias("id_a"), F.col("doc_id").alias("id_b"), F.lit(1.0).alias("likeness"))
    return class_pairs(classes, threshold).unionByName(copies)


def class_pairs(classes: DataFrame, threshold: float = 0.8) -> DataFrame:
    """Pairs (id_a, id_b, likeness), id_a < id_b, of distinct sets (id, sigs) at or above the threshold."""
    prefix = cut(_prefixes(classes, threshold), "prefixes")
    left = prefix.select(F.col("id").alias("id_a"), F.col("n").alias("n_a"), F.explode(F.array("part", F.col("part") + 1)).alias("part"), "s")
    right = prefix.select(F.col("id").alias("id_b"), F.col("n").alias("n_b"), "part", "s")
    ahead = (F.col("n_a") < F.col("n_b")) | ((F.col("n_a") == F.col("n_b")) & (F.col("id_a") < F.col("id_b")))
    found = left.join(right, ["part", "s"]).where(ahead & (F.col("n_a") >= F.lit(threshold) * F.col("n_b"))).select("id_a", "id_b").distinct()
    whole = found.join(classes.select(F.col("id").alias("id_a"), F.col("sigs").alias("x")), "id_a").join(classes.select(F.col("id").alias("id_b"), F.col("sigs").alias("y")), "id_b")
    linked = whole.withColumn("likeness", likeness("x", "y", threshold)).where(F.col("likeness") >= threshold)
    return linked.select(F.least("id_a", "id_b").alias("id_a"), F.greatest("id_a", "id_b").alias("id_b"), "likeness")


def with_next(docs: DataFrame, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """Deal (ord, text, ...) into ordered buckets: adds b1, b2 and guard.

    Buckets are bounded by ids that occur, found by two levels of quantiles, so no task sorts
    the table and any spread of ids gives even buckets. The first document of each
    bucket is repeated, as a guard, at the end of the bucket before (of the last
    bucket, for the very first), so every successor is found within a bucket.
    """
    total = docs.count()
    buckets = max(1, -(-total // bucket_rows))
    coarse = min(1000, math.isqrt(buckets - 1) + 1)
    fine = -(-buckets // coarse)
    cuts: list[int] = []
    if coarse > 1:
        at = [i / coarse for i in range(1, coarse)]
        cuts = sorted(set(docs.agg(F.percentile_approx("ord", F.array(*map(F.lit, at)), 20 * coarse)).first()[0]))
    b1 = F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c <= F.col("ord"))) if cuts else F.lit(0)
    steps = F.array(*[F.lit(i / fine) for i in range(fine)])
    levels = docs.select(b1.alias("b1"), "ord").groupBy("b1").agg(
        F.array_sort(F.array_distinct(F.concat(F.array(F.min("ord")), F.percentile_approx("ord", steps, 20 * fine)))).alias("firsts")
    )
    ring = Window.orderBy("b1")  # at most 1,000 rows
    whole = Window.partitionBy()
    last = F.struct(F.col("b1").alias("b1"), F.size("firsts").alias("b2"))
    levels = cut(levels.withColumn("before", F.coalesce(F.lag(last).over(ring), F.max(last).over(whole))), "levels")
    placed = docs.withColumn("b1", b1).join(F.broadcast(levels), "b1")
    b2 = F.size(F.filter("firsts", lambda f: f <= F.col("ord")))
    placed = placed.withColumn("b2", b2)
    own = F.struct(F.col("b1").alias("b1"), F.col("b2").alias("b2"), F.lit(False).alias("guard"))
    prior = F.when(F.col("b2") > 1, F.struct(F.col("b1").alias("b1"), (F.col("b2") - 1).alias("b2"))).otherwise(F.col("before"))
    guard = F.struct(prior["b1"].alias("b1"), prior["b2"].alias("b2"), F.lit(True).alias("guard"))
    first = F.col("ord") == F.element_at("firsts", F.col("b2"))
    spread = placed.withColumn("__at", F.explode(F.when(first, F.array(own, guard)).otherwise(F.array(own))))
    return spread.drop("b1", "b2", "firsts", "before").select("*", "__at.*").drop("__at")


def fingerprint_documents(docs: DataFrame, anchors: list[str] | None = None, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """Fingerprints of each whole text and of its edited text, and how alike they are.

    Returns doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited,
    near_next, n_signatures, length_part. The edited text ends in the opening of the next
    document by doc_id instead of its own last quarter (the last document is followed
    by the first). Null texts count as empty; rows that repeat a doc_id follow each other
    by text; null ids come first. Texts without words have an empty fingerprint, and two
    of them are wholly alike. An empty table gives an empty result; other columns are not read.
    """
    anchors = common_words(docs) if anchors is None else anchors
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.coalesce(F.col("doc_id").cast("long"), F.lit(_FIRST)).alias("ord"))
    dealt = with_next(rows, bucket_rows).repartition("b1", "b2")
    signed = with_signatures(dealt, "text", "sigs", anchors)
    order = Window.partitionBy("b1", "b2").orderBy("guard", "ord", "text")
    paired = signed.select(
        "doc_id", "text", "sigs", "guard", F.lead("text").over(order).alias("next_text"), F.lead("sigs").over(order).alias("next_sigs")
    ).where(~F.col("guard"))
    n = F.length("text")
    quarter = F.floor(n / 4).cast("int")
    edited = paired.select(
        "doc_id", n.cast("long").alias("n_chars"), "sigs", "next_sigs",
        F.concat(F.substring(F.col("text"), F.lit(1), n - quarter), F.substring(F.col("next_text"), F.lit(1), quarter)).alias("edited"),
    )
    done = with_signatures(edited, "edited", "edited_sigs", anchors)
    return done.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"),
        fingerprint("sigs").alias("fingerprint"), fingerprint("edited_sigs").alias("edited_fingerprint"),
        likeness("sigs", "edited_sigs").alias("near_edited"), likeness("sigs", "next_sigs").alias("near_next"),
        F.size("sigs").alias("n_signatures"), length_part(F.size("sigs"), 0.8).alias("length_part"),
    )


def similar_documents(docs: DataFrame, threshold: float = 0.8, anchors: list[str] | None = None) -> DataFrame:
    """The similarity join over all documents: doc_id, class_id, n_links, best.

    class_id is the least doc_id of the same fingerprint, n_links the number of other fingerprints whose likeness reaches
    `threshold`, best the greatest such likeness (0 without links). Texts without words are in no class
    (null) and link with nothing. Rows without doc_id, and repeated rows, keep their place; an empty table gives an empty result.
    """
    anchors = common_words(docs) if anchors is None else anchors
    signed = cut(with_signatures(docs.select("doc_id", "text"), "text", "sigs", anchors).select("doc_id", "sigs"), "signed")
    classes = cut(signed.where("doc_id is not null and size(sigs) > 0").groupBy("sigs").agg(F.min("doc_id").alias("id")), "spots")
    pairs = cut(class_pairs(classes, threshold), "pairs")
    ends = pairs.select(F.inline(F.array(*[F.struct(F.col(c).alias("id"), "likeness") for c in ("id_a", "id_b")])))
    links = ends.groupBy("id").agg(F.count("*").alias("n_links"), F.max("likeness").alias("best"))
    known = signed.join(classes, "sigs", "left").select("doc_id", F.when(F.col("doc_id").isNotNull(), F.col("id")).alias("class_id"))
    return known.join(links.withColumnRenamed("id", "class_id"), "class_id", "left").select(
        "doc_id", "class_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("best", F.lit(0.0)).alias("best")
    )
