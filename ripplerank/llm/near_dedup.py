"""Near-duplicate removal by a chosen-path similarity join over word shingles.

Documents with equal shingle sets are one class. Every class enters one node of each of
several independent trees: the node of a minwise token. In a node, all members are
measured against its least member by their tokens. Those close to it form its core and
leave the node; those that could still link with a core member are attached to it. What
remains is compared exhaustively where it is small, and otherwise branched by further
minwise tokens, chosen by the node itself. So dense groups cost one row per member and
node, and sparse nodes grow apart.

Cores that share members are one cluster. Within a cluster and what is attached to
it, links are decided on the full shingle sets, in blocks of bounded size, and only a spanning
part of them leaves a task; connectivity, not the number of links, is what is asked for.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import components, cut
from .textnum import mix, rolling, slices, word_hashes

#: Least similarity of a link, in hundredths.
PERCENT = 80
#: Chance with which a pair at the least similarity should meet in some node.
RECALL = 0.99999
#: Minwise tokens of a class.
TOKENS = 64
#: Levels below the roots, and branches of a large node at each.
DEPTH, BRANCHES = 3, 2
#: Members that may remain in a node for an exhaustive comparison.
SMALL = 48
#: Of 64 tokens, as many agree with a node's least member in its core and in an exhaustively compared pair (a link falls
#: under it with a chance of 1e-8); and as many in what is attached to a core: a link of a core
#: member keeps four fifths of its agreements, 25 or more expected, in each of the trees.
CORE, ATTACHED = 32, 18
#: Bytes of shingle sets, and sets, in a block.
BLOCK_BYTES, BLOCK_SETS = 4 << 20, 1024

_FACTORS = mix(np.arange(1, TOKENS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def trees_for(percent: int = PERCENT, recall: float = RECALL) -> int:
    """Trees after which a pair at the least similarity has met with chance `recall`, on the deepest paths."""
    s = percent / 100
    one = s * (1 - (1 - s) ** BRANCHES) ** DEPTH
    return min(TOKENS, math.ceil(math.log(1 - recall) / math.log(1 - one)))


def _shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text; fewer than k words make one shingle, none make none."""
    h, begin = word_hashes(data, offsets)
    roll = rolling(h, k)
    for a, b in zip(begin[:-1], begin[1:]):
        if b - a >= k:
            yield np.unique(roll[a : b - k + 1])
        elif b > a:
            # Shorter sequences hash apart from whole shingles.
            yield mix(rolling(h[a:b], int(b - a)) + np.uint64(b - a))
        else:
            yield np.zeros(0, np.uint64)


def _sketches(docs: DataFrame, k: int) -> DataFrame:
    """doc_id, n, identity of the shingle set (128 bits) and its minwise tokens, from whole texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, data, offsets in slices(batch, "text"):
                sets = list(_shingle_sets(data, offsets, k))
                sizes = np.array([len(s) for s in sets])
                tokens = np.zeros((len(sets), TOKENS), np.int32)
                held = np.flatnonzero(sizes)
                lo, hi = np.zeros(len(sets), np.uint64), np.zeros(len(sets), np.uint64)
                if len(held):
                    flat = np.concatenate([sets[i] for i in held])
                    runs = np.cumsum(sizes[held]) - sizes[held]
                    for t in range(TOKENS):
                        least = np.minimum.reduceat(flat * _FACTORS[t], runs)
                        tokens[held, t] = (mix(least) >> np.uint64(33)).astype(np.int32)
                    lo[held] = np.add.reduceat(mix(flat + np.uint64(1)), runs)
                    hi[held] = np.add.reduceat(mix(flat ^ np.uint64(0xA5A5A5A5A5A5A5A5)), runs)
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(lo.view(np.int64)), pa.array(hi.view(np.int64)),
                     pa.FixedSizeListArray.from_arrays(pa.array(tokens.ravel()), TOKENS).cast(pa.list_(pa.int32()))],
                    ["doc_id", "n", "lo", "hi", "tokens"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
        run, "doc_id bigint, n bigint, lo bigint, hi bigint, tokens array<int>"
    )


def _sets(docs: DataFrame, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, data, offsets in slices(batch, "text"):
                packed = [s.tobytes() for s in _shingle_sets(data, offsets, k)]
                yield pa.RecordBatch.from_arrays([part.column("cid"), pa.array(packed, pa.large_binary()).cast(pa.binary())], ["cid", "grams"])

    return docs.select("cid", "text").mapInArrow(run, "cid bigint, grams binary")


def _agree(x: str, y: str) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a == b).cast("int")), F.lit(0), lambda s, v: s + v)


def _links_within(sets: list[np.ndarray], percent: int) -> np.ndarray:
    """Pairs (positions) that link, a spanning part of them, decided on whole sets.

    Shingles held by few sets are counted pair by pair, the others by products of their
    incidence, a bounded number of columns at a time.
    """
    d = len(sets)
    size = np.array([len(x) for x in sets])
    _, column, held = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(d), size)
    both = np.zeros((d, d), np.float32)
    order = np.argsort(column, kind="stable")
    row, starts = row[order], np.cumsum(held) - held
    few = 8
    for n in range(2, few + 1):
        at = starts[held == n]
        for i in range(n):
            for j in range(i + 1, n):
                np.add.at(both, (row[at + i], row[at + j]), 1)
    many = np.flatnonzero(held > few)
    for part in np.array_split(many, max(1, -(-len(many) * d // (1 << 22)))) if len(many) else ():
        x = np.zeros((d, len(part)), np.float32)
        n = held[part]
        spots = np.arange(int(n.sum())) + np.repeat(starts[part] - (np.cumsum(n) - n), n)
        x[row[spots], np.repeat(np.arange(len(part)), n)] = 1
        both += np.triu(x @ x.T, 1)
    found = []
    for at in range(0, d, 256):
        rows = both[at : at + 256]
        i, j = np.nonzero(100 * rows >= percent * (size[at : at + 256, None] + size[None, :] - rows))
        ahead = j > i + at
        found.append((i[ahead] + at, j[ahead]))
    i, j = (np.concatenate(x) for x in zip(*found))
    parent = list(range(d))

    def root(v: int) -> int:
        while parent[v] != v:
            parent[v] = parent[parent[v]]
            v = parent[v]
        return v

    out = []
    for a, b in zip(i.tolist(), j.tolist()):
        if (ra := root(a)) != (rb := root(b)):
            parent[max(ra, rb)] = min(ra, rb)
            out.append((a, b))
    return np.array(out, np.int64).reshape(-1, 2)


def _blocks(members: Column, shingles: Column) -> Column:
    return F.ceil(F.greatest(shingles * 8 / F.lit(BLOCK_BYTES), members / F.lit(BLOCK_SETS))).cast("int")


def _linked_to_leaders(members: DataFrame, stars: DataFrame, grams: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between members (cid) and the leader that each resembles most, decided on full sets: one pair a member."""
    best = stars.join(members.select(F.col("cid").alias("b")), "b", "left_semi").groupBy("b").agg(F.max(F.struct("agree", (-F.col("a")).alias("a"))).alias("x"))
    pairs = best.select((-F.col("x.a")).alias("a"), "b")
    both = pairs.join(grams.select(F.col("cid").alias("a"), F.col("grams").alias("x")), "a").join(grams.select(F.col("cid").alias("b"), F.col("grams").alias("y")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hit = []
            for x, y in zip(batch.column("x"), batch.column("y")):
                x, y = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                common = len(np.intersect1d(x, y, assume_unique=True))
                hit.append(100 * common >= percent * (len(x) + len(y) - common))
            yield batch.select(["a", "b"]).filter(pa.array(hit, pa.bool_()))

    return both.select("a", "b", "x", "y").mapInArrow(run, "a bigint, b bigint")


def _open_units(rows: DataFrame, points: DataFrame, linked: DataFrame) -> DataFrame:
    """Units of work (grp, cid, i, j) of large groups (grp, cid) whose links to leaders are known.

    The largest part of a group that those links hold together is settled: only what is left is compared, with itself and with
    the settled part. Groups in one part need nothing more, so work grows with the members times the blocks of what is left.
    """
    parts = components(linked, "led").select(F.col("node").alias("cid"), "component")
    placed = cut(rows.join(parts, "cid", "left").join(points.select("cid", "n"), "cid").select("grp", "cid", "n", F.coalesce("component", "cid").alias("part")), "parts")
    sizes = placed.groupBy("grp", "part").agg(F.count("*").alias("m"), F.sum("n").alias("n"))
    whole = sizes.groupBy("grp").agg(F.max(F.struct("m", "part", "n")).alias("main"), F.sum("m").alias("m"), F.sum("n").alias("n")).where("m > main.m")
    load = whole.select("grp", F.col("main.part").alias("main"), _blocks(F.col("main.m"), F.col("main.n")).alias("settled"), _blocks(F.col("m") - F.col("main.m"), F.col("n") - F.col("main.n")).alias("left"))
    mine = F.col("part") == F.col("main")
    at = F.xxhash64("cid")
    own = F.when(mine, F.col("left") + F.pmod(at, F.col("settled"))).otherwise(F.pmod(at, F.col("left"))).cast("int")
    last = F.when(mine, F.col("left")).otherwise(F.col("left") + F.col("settled")) - 1
    dealt = placed.join(load, "grp").select("grp", "cid", own.alias("own"), F.explode(F.filter(F.sequence(F.lit(0), last), lambda x: x != own)).alias("other"))
    return dealt.select("grp", "cid", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))


def _confirm(groups: DataFrame, docs: DataFrame, points: DataFrame, k: int, percent: int, stars: DataFrame) -> DataFrame:
    """Links (a, b) among the members (grp, cid) of each group, on their full sets.

    Texts are read again only for members. A group within a block is one unit of work. In a larger one, members are first
    compared with the leader that they resemble most (`stars`: a, b, agree), and then only where that leaves it in parts.
    """
    sized = groups.join(points.select("cid", "n"), "cid")
    load = sized.groupBy("grp").agg(F.count("*").alias("m"), _blocks(F.count("*"), F.sum("n")).alias("blocks")).where("m > 1")
    rows = cut(groups.join(load, "grp").select("grp", "cid", "blocks"), "units", {"large": F.count(F.when(F.col("blocks") > 1, 1))})

    def sets(members: DataFrame) -> DataFrame:
        wanted = members.select("cid").distinct()
        return _sets(docs.select(F.col("doc_id").cast("long").alias("cid"), "text").join(wanted, "cid", "left_semi"), k)

    units = rows.where("blocks = 1").select("grp", "cid", F.lit(0).alias("i"), F.lit(0).alias("j"))
    linked = None
    if rows.facts.get("large"):
        large = rows.where("blocks > 1").select("grp", "cid")
        members = cut(large.select("cid").distinct(), "large")
        grams = sets(members)  # a leader is in the group of all that it leads closely
        linked = cut(_linked_to_leaders(members, stars, grams, percent), "linked")
        units = units.unionByName(_open_units(large, points, linked))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, ids, sets = None, [], []

        def done() -> pa.RecordBatch:
            found = _links_within(sets, percent)
            at = np.array(ids)
            return pa.RecordBatch.from_arrays([pa.array(at[found[:, 0]], pa.int64()), pa.array(at[found[:, 1]], pa.int64())], ["a", "b"])

        for batch in batches:
            cols = [batch.column(c).to_pylist() for c in ("grp", "i", "j", "cid")]
            for g, i, j, cid, x in zip(*cols, batch.column("grams")):
                if (g, i, j) != key:
                    if len(ids) > 1:
                        yield done()
                    key, ids, sets = (g, i, j), [], []
                ids.append(cid)
                sets.append(np.frombuffer(x.as_py(), np.uint64))
        if len(ids) > 1:
            yield done()

    dealt = units.join(sets(rows), "cid").repartition("grp", "i", "j").sortWithinPartitions("grp", "i", "j", "cid")
    found = dealt.select("grp", "i", "j", "cid", "grams").mapInArrow(run, "a bigint, b bigint")
    return found if linked is None else found.unionByName(linked)


def _repeats(docs: DataFrame) -> bool:
    return not docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").isEmpty()


def near_dedup(docs: DataFrame, k: int = 5, percent: int = PERCENT, recall: float = RECALL) -> DataFrame:
    """Classes of near-duplicate documents: doc_id, n_shingles, component_id, kept for every row of `docs`.

    A text's set holds its distinct shingles of `k` words (split at ASCII white space, A-Z
    lower-cased); a shorter text is one shingle. Texts link when
    100 * intersection >= percent * union. component_id is the least doc_id reachable over links, and
    that document is kept. Null and blank texts have no shingles and link with
    nothing. Rows with a null doc_id link with nothing, have a null component and are kept.
    Rows that repeat a doc_id are taken as one document: their texts all count towards
    the links of that id. An empty table gives an empty result; other columns are not read.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if not _repeats(docs):
        return _near_unique(docs, k, percent, recall)
    # Every (doc_id, text) is a document of its own first; the ids tie their texts together afterwards.
    key = F.xxhash64("doc_id", F.coalesce("text", F.lit("")))
    found = _near_unique(docs.where("doc_id is not null").select(key.alias("doc_id"), "text").groupBy("doc_id").agg(F.min("text").alias("text")), k, percent, recall)
    found = cut(found.select(F.col("doc_id").alias("key"), "n_shingles", F.col("component_id").alias("part")), "keyed")
    own = docs.select("doc_id", key.alias("key"))
    parts = own.where("doc_id is not null").join(found, "key").select("doc_id", "part").distinct()
    least = parts.groupBy("part").agg(F.min("doc_id").alias("least"))
    ids = components(parts.join(least, "part").select(F.col("doc_id").alias("a"), F.col("least").alias("b")), "ids").withColumnRenamed("node", "doc_id")
    sizes = docs.where("doc_id is null")
    lone = _sketches(sizes, k).select("doc_id", F.col("n").alias("n_shingles"), F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    rows = own.where("doc_id is not null").join(found.select("key", "n_shingles"), "key").join(ids, "doc_id", "left")
    component = F.coalesce("component", "doc_id")
    return rows.select("doc_id", "n_shingles", component.alias("component_id"), (F.col("doc_id") == component).alias("kept")).unionByName(lone)


def _near_unique(docs: DataFrame, k: int, percent: int, recall: float) -> DataFrame:
    rows = cut(_sketches(docs, k), "sketches")
    classes = cut(
        rows.where("n > 0 and doc_id is not null").groupBy("lo", "hi", "n").agg(F.min("doc_id").alias("cid"), F.first("tokens").alias("tokens")), "classes"
    )
    points = classes.select("cid", "n", "tokens")
    trees = trees_for(percent, recall)
    nodes = points.select("cid", F.posexplode(F.slice("tokens", 1, trees)).alias("tree", "token")).select("cid", F.xxhash64("tree", "token").alias("node"))
    core = attached = stars = None
    for level in range(DEPTH + 1):
        leads = nodes.groupBy("node").agg(F.count("*").alias("size"), F.min("cid").alias("lead")).where("size > 1")
        met = cut(nodes.join(leads.select("node", "lead"), "node").where("cid <> lead"), "met")
        # Members meet the same least member in many trees; each such pair is measured once.
        pairs = met.select("cid", "lead").distinct().join(points.select("cid", "tokens"), "cid")
        pairs = pairs.join(points.select(F.col("cid").alias("lead"), F.col("tokens").alias("held")), "lead")
        pairs = cut(pairs.select("cid", "lead", _agree("tokens", "held").alias("agree")), "measured")
        measured = met.join(pairs, ["cid", "lead"])
        near = pairs.where(F.col("agree") >= CORE).select(F.col("lead").alias("a"), F.col("cid").alias("b"))
        off = pairs.where((F.col("agree") >= ATTACHED) & (F.col("agree") < CORE)).select(F.col("lead").alias("a"), F.col("cid").alias("b"))
        led = pairs.where(F.col("agree") >= CORE).select(F.col("lead").alias("a"), F.col("cid").alias("b"), "agree")
        core, attached, stars = (near, off, led) if core is None else (core.unionByName(near), attached.unionByName(off), stars.unionByName(led))
        rest = cut(measured.where(F.col("agree") < CORE).select("node", "cid"), "rest")
        left = rest.groupBy("node").agg(F.count("*").alias("m")).where("m > 1")
        last = level == DEPTH
        small, large = (left, left.limit(0)) if last else (left.where(F.col("m") <= SMALL), left.where(F.col("m") > SMALL))
        x = cut(rest.join(small.select("node"), "node", "left_semi").join(points, "cid"), "small")
        y = x.select("node", F.col("cid").alias("b"), F.col("n").alias("bn"), F.col("tokens").alias("bt"))
        possible = (F.col("cid") < F.col("b")) & (100 * F.least("n", "bn") >= percent * F.greatest("n", "bn")) & (_agree("tokens", "bt") >= CORE)
        core = core.unionByName(x.join(y, "node").where(possible).select(F.col("cid").alias("a"), "b"))
        if last or large.isEmpty():
            break
        picks = F.array_distinct(F.array(*[F.pmod(F.xxhash64("node", F.lit(i)), F.lit(TOKENS)).cast("int") for i in range(BRANCHES)]))
        nodes = cut(
            rest.join(large.select("node"), "node", "left_semi").join(points, "cid").withColumn("pick", F.explode(picks))
            .select("cid", F.xxhash64("node", "pick", F.get(F.col("tokens"), F.col("pick"))).alias("node")), "nodes",
        )
    clusters = components(core, "clusters")
    grouped = clusters.select(F.col("component").alias("grp"), F.col("node").alias("cid"))
    led = attached.distinct().join(clusters.withColumnRenamed("node", "a"), "a", "left").select(F.coalesce("component", "a").alias("grp"), F.col("b").alias("cid"), "a")
    groups = grouped.unionByName(led.select("grp", "cid")).unionByName(led.select("grp", F.col("a").alias("cid"))).distinct()
    joined = components(_confirm(groups, docs, points, k, percent, stars), "cc").withColumnRenamed("node", "cid")
    # Copies meet their class by identity; the class carries its component's least document.
    named = classes.join(joined, "cid", "left").select("lo", "hi", "n", F.coalesce("component", "cid").alias("component_id"))
    out = rows.select("doc_id", "n", "lo", "hi").join(named, ["lo", "hi", "n"], "left")
    own_id = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), own_id.alias("component_id"), F.col("doc_id").eqNullSafe(own_id).alias("kept"))
