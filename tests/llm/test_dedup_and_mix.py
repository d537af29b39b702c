import hashlib
import re

import pytest

from ripplerank.llm import exact_dedup, source_mix

SF = "/root/testdata/sf0.01"


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def test_exact_groups_with_edges(spark):
    rows = [(1, "Ab"), (2, "aB"), (3, "É"), (4, "é"), (5, None), (6, ""), (7, " "), (None, "ab"), (None, "lone"), (9, "x" * 100_000), (8, "X" * 100_000), (2, "ab")]
    df = spark.createDataFrame([(i, t, "k", 0) for i, t in rows], "doc_id long, text string, keep_id string, kept int")
    got = sorted(((r.doc_id, r.keep_id, r.group_size, r.kept, r.text_sha256) for r in exact_dedup.exact_dedup(df).collect()), key=str)
    groups = {}
    for i, t in rows:
        groups.setdefault(lower(t), []).append(i)
    want = []
    for i, t in rows:
        g = groups[lower(t)]
        keep = max((x for x in g if x is not None), default=None)
        want.append((i, keep, len(g), i == keep, hashlib.sha256(lower(t).encode()).hexdigest()))
    assert got == sorted(want, key=str)
    assert exact_dedup.exact_dedup(df.limit(0)).count() == 0


def test_clashing_digests_are_told_apart(spark, monkeypatch):
    from pyspark.sql import functions as F

    monkeypatch.setattr(exact_dedup.F, "sha2", lambda c, n: F.lit("same").cast("string"))
    df = spark.createDataFrame([(1, "a"), (2, "A"), (3, "b")], "doc_id long, text string")
    got = {r.doc_id: (r.keep_id, r.group_size, r.kept) for r in exact_dedup.exact_dedup(df).collect()}
    assert got == {1: (2, 2, False), 2: (2, 2, True), 3: (3, 1, True)}


def water(sizes, weights, share, cap):
    left, capped = share * sum(sizes), set()
    while True:
        free = [i for i in range(len(sizes)) if i not in capped]
        total = sum(weights[i] for i in free)
        target = {i: left * weights[i] / total for i in free} if free else {}
        over = [i for i in free if target[i] > cap * sizes[i]]
        if not over:
            return [cap * sizes[i] if i in capped else target[i] for i in range(len(sizes))]
        capped |= set(over)
        left = share * sum(sizes) - sum(cap * sizes[i] for i in capped)


@pytest.mark.parametrize("weights, share, cap", [((3, 1, 2), 1.5, 2.0), ((1,), 0.5, 2.0), ((5, 1), 2.0, 2.0), ((9, 1, 1, 1), 1.9, 2.0)])
def test_targets_and_taken(spark, weights, share, cap):
    df = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source", "text").unionByName(
        spark.createDataFrame([(9000, None, "null source"), (9001, "", "a b c"), (9002, "", None), (9003, "é", " "), (9004, "z", "q")], "doc_id long, source string, text string"))
    sizes = {}
    longest = {}
    for r in df.collect():
        n = len([w for w in re.split(r"[\x20\x09-\x0d]+", r.text or "") if w])
        sizes[r.source] = sizes.get(r.source, 0) + n
        longest[r.source] = max(longest.get(r.source, 0), n)
    names = sorted((s for s in sizes if s is not None)) + [None]
    want = dict(zip(names, water([sizes[s] for s in names], [weights[i % len(weights)] for i in range(len(names))], share, cap)))
    taken = {}
    rows = source_mix.mix_sources(df, weights, share, cap).collect()
    assert len(rows) == df.count()
    for r in rows:
        assert r.target == pytest.approx(want[r.source]) and r.source_size == sizes[r.source]
        assert r.copies <= -(-cap // 1) and r.taken == r.copies * r.size <= 2 * r.size
        taken[r.source] = taken.get(r.source, 0) + r.taken
    assert all(abs(taken[s] - want[s]) <= longest[s] + 1 for s in names)
    again = source_mix.mix_sources(df.repartition(5), weights, share, cap).collect()
    assert sorted((r.doc_id, r.copies) for r in rows) == sorted((r.doc_id, r.copies) for r in again)


def test_emitting_repeated_rows_and_empty_table(spark):
    df = spark.createDataFrame([(i % 3, f"t {i}", "s", {"k": i}) for i in range(9)] + [(None, "n n", "s", None)], "doc_id long, text string, source string, m map<string,int>")
    drawn = source_mix.mix_sources(df).groupBy("doc_id").sum("copies").collect()
    out = source_mix.emit_mix(df)
    assert out.columns == df.columns
    got = {r[0]: r[1] for r in out.groupBy("doc_id").count().collect()}
    assert got == {r[0]: r[1] for r in drawn if r[1]}
    assert source_mix.mix_sources(df.limit(0)).count() == 0 and source_mix.emit_mix(df.limit(0)).count() == 0
