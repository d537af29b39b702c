import hashlib
import itertools
import re

import pytest

from ripplerank.llm import spot_signatures as S


def split(text):
    return [w for w in re.split(r"[\x00-\x2f\x3a-\x60\x7b-\x7f]+", (text or "").lower()) if w]


def spots(text, anchors, chain=3):
    w = split(text)
    if not w:
        return set()
    out = {("^", *w[:chain])}
    content = [(i, x) for i, x in enumerate(w) if x not in anchors]
    for i, x in enumerate(w):
        if x in anchors:
            after = [y for j, y in content if j > i][:chain]
            if len(after) == chain:
                out.add((x, *after))
    return out


def jaccard(a, b):
    return 1.0 if not a and not b else len(a & b) / len(a | b)


@pytest.mark.parametrize("bucket_rows", [3, 50, 2000])
def test_whole_table_as_brute_force(spark, bucket_rows):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").unionByName(
        spark.createDataFrame([(9_000_000_000, None), (1000, ""), (1001, "ab"), (1002, "éèéèé"), (-5, "the of the of"), (1003, "Y" * 9)], "doc_id long, text string"))
    anchors = S.common_words(docs, 40)
    rows = sorted(docs.collect(), key=lambda r: r.doc_id)
    got = {r.doc_id: r for r in S.fingerprint_documents(docs, anchors, bucket_rows).collect()}
    assert len(got) == len(rows)
    prints = {}
    for r, after in zip(rows, rows[1:] + rows[:1]):
        text, next_text = r.text or "", after.text or ""
        q = len(text) // 4
        edited = text[: len(text) - q] + next_text[:q]
        g = got[r.doc_id]
        a, e, n = (spots(t, anchors) for t in (text, edited, next_text))
        assert (g.n_chars, g.edited_sha256) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
        assert len(g.fingerprint) == 8 * len(a) and g.n_signatures == len(a)
        assert g.near_edited == pytest.approx(jaccard(a, e)) and g.near_next == pytest.approx(jaccard(a, n))
        assert prints.setdefault(text, g.fingerprint) == g.fingerprint


def test_common_words_count_documents(spark):
    docs = spark.createDataFrame([(1, "b a a a"), (2, "B c"), (3, "b a"), (4, None)], "doc_id long, text string")
    assert S.common_words(docs, 2) == ["b", "a"]


def test_ties_nulls_and_empty_table(spark):
    docs = spark.createDataFrame([(None, "zz yy xx ww"), (1, "bbbb"), (1, "aaaa"), (None, None)], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.n_chars, r.edited_sha256) for r in S.fingerprint_documents(docs, ["aa"], 1).collect())
    h = lambda t: hashlib.sha256(t.encode()).hexdigest()
    assert got == sorted([(0, 0, h("")), (0, 11, h("zz yy xx aa")), (1, 4, h("aaab")), (1, 4, h("bbb"))])
    assert S.fingerprint_documents(docs.limit(0)).count() == 0
    one = S.fingerprint_documents(docs.where("text = 'bbbb'"), [], 5).collect()
    assert [r.edited_sha256 for r in one] == [h("bbbb")] and one[0].near_next == 1.0


def test_similar_pairs_as_brute_force(spark):
    import random

    rng = random.Random(3)
    base = [sorted({rng.randrange(10**6) for _ in range(n)}) for n in (3, 40, 41, 90)]
    sets = [*base, base[1], base[1]]
    for b in base * 6:
        s = set(b)
        for _ in range(rng.randrange(1, 12)):
            s.discard(rng.choice(sorted(s)) if s else 0)
            s.add(rng.randrange(10**6))
        sets.append(sorted(s))
    df = spark.createDataFrame([*enumerate(map(list, sets)), (900, []), (None, [1])], "doc_id long, sigs array<int>")
    got = {(r.id_a, r.id_b): r.likeness for r in S.similar_pairs(df, 0.6).collect()}
    rep = {i: min(j for j, t in enumerate(sets) if t == s) for i, s in enumerate(sets)}
    want = {(rep[i], i): 1.0 for i in rep if rep[i] != i}
    for i, j in itertools.combinations(sorted(set(rep.values())), 2):
        if (x := jaccard(set(sets[i]), set(sets[j]))) >= 0.6:
            want[i, j] = x
    assert got == pytest.approx(want) and len(want) > 10


def test_similarity_join_over_documents_as_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    odd = spark.createDataFrame([(9000, None), (9001, ""), (9002, "the same words of a text here"), (9003, "the same words of a text here"), (None, "the same words of a text here")], docs.schema)
    docs = docs.unionByName(odd)
    anchors = S.common_words(docs)
    sigs = {}
    for r in S.with_signatures(docs, "text", "sigs", anchors).collect():
        if r.doc_id is not None:
            sigs[r.doc_id] = frozenset(r.sigs)
    classes = {}
    for d, s in sorted(sigs.items()):
        if s:
            classes.setdefault(s, d)
    links = {}
    for a, b in itertools.combinations(classes, 2):
        share = len(a & b) / len(a | b)
        if share >= 0.8:
            links.setdefault(a, []).append(share), links.setdefault(b, []).append(share)
    rows = S.similar_documents(docs, anchors=anchors).collect()
    assert len(rows) == len(sigs) + 1 and links
    for r in rows:
        s = sigs.get(r.doc_id)
        want = (classes.get(s), len(links.get(s, [])), max(links.get(s, [0.0]))) if r.doc_id is not None else (None, 0, 0.0)
        assert (r.class_id, r.n_links) == want[:2] and abs(r.best - want[2]) < 1e-12
    assert S.similar_documents(docs.limit(0)).count() == 0
