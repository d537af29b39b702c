import random
import re

import pytest

from ripplerank.llm import near_dedup as N
from ripplerank.llm.common import components


def shingles(text, k):
    w = [x for x in re.split(r"[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if x]
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])


def brute(docs, k, percent=80):
    sets = {i: shingles(t, k) for i, t in docs.items()}
    where = {}
    for i, s in sets.items():
        for g in s:
            where.setdefault(g, set()).add(i)
    parent = {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, s in sets.items():
        near = {}
        for g in s:
            for j in where[g]:
                if j < i:
                    near[j] = near.get(j, 0) + 1
        for j, both in near.items():
            if 100 * both >= percent * len(s | sets[j]):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return {i: (len(sets[i]), root(i)) for i in sets}


def planted(seed, groups=6, copies=60, length=120):
    """Groups of near copies around the threshold, chains whose ends do not link, and texts sharing one passage."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefg") for _ in range(5))
    passage, docs = [word() for _ in range(60)], {}
    for g in range(groups):
        base = [word() for _ in range(length)]
        for _ in range(copies):
            w = list(base)
            for _ in range(rng.randrange(0, 5)):
                w[rng.randrange(length)] = word()
            docs[len(docs)] = " ".join(w)
            if rng.random() < 0.2:
                base = w
    for _ in range(300):
        docs[len(docs)] = " ".join([word() for _ in range(rng.randrange(40, 90))] + passage)
    return docs


@pytest.mark.parametrize("k, small", [(4, 48), (5, 4)])
def test_groups_as_brute_force(spark, k, small, monkeypatch):
    monkeypatch.setattr(N, "SMALL", small)
    monkeypatch.setattr(N, "BLOCK_SETS", small)
    docs = planted(k) | {5000: None, 5001: "", 5002: "Two  words", 5003: "two\twords", 5004: "two", 5005: " \n "}
    df = spark.createDataFrame([(i, t, 1) for i, t in docs.items()], "doc_id long, text string, n int")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in N.near_dedup(df, k=k).collect()}
    want = brute(docs, k)
    assert got == want
    assert len({c for _, c in want.values()}) < len(want) - 100


def test_given_documents_as_brute_force(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = N.near_dedup(df, k=4).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in rows} == brute({r.doc_id: r.text for r in df.collect()}, 4)
    assert all(r.kept == (r.doc_id == r.component_id) for r in rows)


def test_null_ids_repeats_and_empty_table(spark):
    text = " ".join(f"w{i}" for i in range(50))
    other = " ".join(f"v{i}" for i in range(50))
    df = spark.createDataFrame([(None, text), (7, text), (7, other), (9, other + " x"), (3, "alone here")], "doc_id long, text string")
    got = sorted((str(r.doc_id), r.component_id, r.kept) for r in N.near_dedup(df).collect())
    assert got == sorted([("None", None, True), ("7", 7, True), ("7", 7, True), ("9", 7, False), ("3", 3, True)])
    assert N.near_dedup(df.limit(0)).count() == 0


@pytest.mark.parametrize("seed", range(4))
def test_links_on_whole_sets(seed):
    import numpy as np

    rng = np.random.default_rng(seed)
    base = rng.integers(0, 1 << 60, 80)
    sets = [np.unique(np.concatenate([rng.permutation(base)[: rng.integers(60, 81)], rng.integers(0, 1 << 60, rng.integers(0, 12))])).astype(np.uint64) for _ in range(40)]
    sets += [np.unique(rng.integers(0, 1 << 60, 5)).astype(np.uint64) for _ in range(5)]
    parent = list(range(len(sets)))

    def root(v):
        return v if parent[v] == v else root(parent[v])

    for i, x in enumerate(sets):
        for j, y in enumerate(sets[:i]):
            both = len(np.intersect1d(x, y))
            if 100 * both >= 80 * (len(x) + len(y) - both):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    want = [root(i) for i in range(len(sets))]
    parent = list(range(len(sets)))
    for a, b in N._links_within(sets, 80):
        assert root(a) != root(b)
        parent[max(root(a), root(b))] = min(root(a), root(b))
    assert [root(i) for i in range(len(sets))] == want and len(set(want)) < len(sets)


def test_trees_reach_the_recall():
    assert N.trees_for(80, 0.9) < N.trees_for(80, 0.99999) <= 16


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 200), (200, 150), (5, 5), (None, 3), (300, 300)] + [(1000, j) for j in range(1001, 1100)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 150: 100, 200: 100, **{j: 1000 for j in range(1000, 1100)}}
    assert components(spark.createDataFrame([], "a string, b string")).count() == 0


def test_all_texts_of_a_repeated_id_count(spark):
    a, b = (" ".join(f"{x}{i}" for i in range(50)) for x in "ab")
    for first, second in ((a, b), (b, a)):
        df = spark.createDataFrame([(7, first), (7, second), (9, b + " x"), (11, a + " x"), (12, "far away from all of it"), (None, a)], "doc_id long, text string")
        got = sorted(((r.doc_id, r.component_id, r.kept) for r in N.near_dedup(df).collect()), key=str)
        assert got == sorted([(7, 7, True), (7, 7, True), (9, 7, False), (11, 7, False), (12, 12, True), (None, None, True)], key=str)


def test_links_beside_a_leader_are_found(spark):
    """The third text lacks just the words that the second shares with the first, so only the other two link with it at its side."""
    rows = []
    for n in range(30):
        w = [f"w{n}_{i}" for i in range(100)]
        second = w[:88] + [f"s{n}_{i}" for i in range(12)]
        third = w[12:88] + second[88:] + w[:0]
        rows += [(10 * n, " ".join(w)), (10 * n + 1, " ".join(second)), (10 * n + 2, " ".join(third))]
    texts = dict(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute(texts, 4)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in N.near_dedup(df, k=4).collect()}
    assert got == {d: tuple(x) for d, x in want.items()}


@pytest.mark.parametrize("seed, most", [(3, 8), (5, 1), (6, 40)])
def test_groups_beyond_a_block_lose_no_link(spark, monkeypatch, seed, most):
    monkeypatch.setattr(N, "BLOCK_SETS", most)
    docs = planted(seed)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in N.near_dedup(df, k=4).collect()}
    assert got == brute(docs, 4)


def test_a_group_held_together_by_its_leader_needs_no_more_units(spark):
    rows = spark.createDataFrame([(1, c) for c in range(1, 40)] + [(2, c) for c in range(100, 140)], "grp long, cid long")
    points = spark.createDataFrame([(c, 10) for c in [*range(1, 40), *range(100, 140)]], "cid long, n long")
    linked = spark.createDataFrame([(1, c) for c in range(2, 40)] + [(100, c) for c in range(101, 137)], "a long, b long")
    units = N._open_units(rows, points, linked).collect()
    assert {r.grp for r in units} == {2} and len(units) == 40  # three left in one block, beside one settled block
