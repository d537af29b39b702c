"""Each stage on its own input against brute force, over whole small tables."""

import hashlib
import re

import numpy as np
import pytest

import corpus_pipeline as C
from ripplerank.llm import common, lang_id, source_mix
from tests.llm.test_near_dedup import brute

SF = "/root/testdata/sf0.01"


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


@pytest.fixture(scope="module")
def stages(spark):
    docs = common.table(spark, SF, "documents")
    odd = spark.createDataFrame([(5000, None, "en", "src1", 0), (5001, "", None, None, 0), (5002, "12345 !!", "en", "src1", 8)], docs.schema)
    docs = common.cut(docs.unionByName(odd), "t")
    out = [docs]
    for name, stage in C.STAGES:
        out.append(common.cut(stage(spark, out[-1], SF), name))
    return out


def ids(df):
    return sorted(r.doc_id for r in df.select("doc_id").collect())


def test_columns_and_order(stages):
    assert [n for n, _ in C.STAGES] == ["language_id", "exact_dedup", "near_dedup", "source_mix", "bpe"]
    assert all(df.columns == stages[0].columns for df in stages[:-1])


def test_language_stage_drops_only_texts_without_letters(stages):
    gone = set(ids(stages[0])) - set(ids(stages[1]))
    texts = {r.doc_id: r.text or "" for r in stages[0].collect()}
    assert {5000, 5001, 5002} <= gone
    assert len(gone - {d for d, t in texts.items() if not any(c.isalpha() for c in t)}) <= 0.005 * len(texts)


def test_exact_stage(stages):
    best = {}
    for r in stages[1].collect():
        best[lower(r.text)] = max(best.get(lower(r.text), r.doc_id), r.doc_id)
    assert ids(stages[2]) == sorted(best.values())


def test_near_stage(stages):
    want = brute({r.doc_id: r.text for r in stages[2].collect()}, 5)
    assert ids(stages[3]) == sorted({c for _, c in want.values()})


def test_mix_stage(stages):
    drawn = {r.doc_id: r.copies for r in source_mix.mix_sources(stages[3]).collect()}
    assert ids(stages[4]) == sorted(d for d, n in drawn.items() for _ in range(n))
    assert max(drawn.values()) <= 2


def test_encoding_stage(stages):
    tokenizers = pytest.importorskip("tokenizers")
    library = tokenizers.Tokenizer.from_file(pytest.importorskip("public_tokenizers").path("word_bpe_49k.json"))
    texts = {r.doc_id: r.text for r in stages[4].collect()}
    rows = stages[5].collect()
    assert sorted(r.doc_id for r in rows) == ids(stages[4])
    for r in rows:
        found = library.encode(texts[r.doc_id], add_special_tokens=False).ids
        assert r.ids_sha256 == hashlib.sha256(np.array(found, "<u4").tobytes()).hexdigest()


def test_held_out_accuracy(spark):
    docs = common.table(spark, SF, "documents")
    model = lang_id.fit(lang_id.train_split(docs))
    rows = lang_id.identify(docs, model).where(lang_id.held_out()).select("lang", "lang_pred", "score").collect()
    assert np.mean([r.lang == r.lang_pred for r in rows]) > 0.97


def test_language_edges(spark):
    df = spark.createDataFrame([(1, "a é b", "x"), (2, None, "x"), (3, "", "x"), (4, "1 2 !", None), (None, "the the", None)], "doc_id long, text string, score string")
    none = lang_id.fit(df.limit(0).selectExpr("doc_id", "text", "score as lang"))
    assert {r.lang_pred for r in lang_id.identify(df.drop("score"), none).collect()} == {"und"}
    train = spark.createDataFrame([(i, t, x) for i in range(30) for t, x in (("the cat and that hat", "en"), ("der hund und das", "de"))], "doc_id long, text string, lang string")
    model = lang_id.fit(train)
    got = {(r.doc_id, r.lang_pred) for r in lang_id.identify(df.drop("score"), model).collect()}
    assert {(2, "und"), (3, "und"), (4, "und"), (None, "en")} <= got
    one = lang_id.fit(train.where("lang = 'en'"))
    assert {r.lang_pred for r in lang_id.identify(df.drop("score"), one).where("doc_id = 1").collect()} == {"en"}


@pytest.mark.parametrize("n", [2, 3, 4, 5, 12])
def test_codewords_differ(n):
    code = lang_id.codewords(n)
    assert code.shape[0] == n
    least = min((a != b).sum() for i, a in enumerate(code) for b in code[:i])
    assert least >= (1 if n == 2 else 2 if n == 3 else 4)


def test_bit_errors_are_corrected():
    code = lang_id.codewords(4)
    model = lang_id.LanguageModel(list("abcd"), code, np.zeros((1, code.shape[1])), np.ones(code.shape[1]), np.ones(code.shape[1]))
    for i, word in enumerate(code):
        for b in range(len(word)):
            margins = word.astype(float).copy()
            margins[b] *= -1
            best, sure = model.decode(margins[None])
            assert best[0] == i and 0 < sure[0] < 1


def test_repeated_and_null_ids_are_decided_row_by_row(spark):
    rows = [(5, "abc x", "en", "s", 5), (5, "zzz y", "en", "s", 5), (9, "ABC x", "en", "s", 5), (7, "dup row", "en", "s", 7), (7, "dup row", "en", "s", 7), (None, "same text", None, None, 4), (None, "same text", None, None, 4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    kept = C.drop_exact_copies(spark, docs, SF)
    assert kept.columns == docs.columns
    got = sorted(((r.doc_id, r.text) for r in kept.collect()), key=str)
    assert got == sorted([(5, "zzz y"), (9, "ABC x"), (7, "dup row"), (None, "same text")], key=str)
    again = sorted(((r.doc_id, r.text) for r in C.drop_near_copies(spark, kept, SF).collect()), key=str)
    assert again == got


def test_extra_columns_with_the_operators_own_names(spark):
    words = "the cat and that hat sat on this mat with some other things"
    docs = spark.createDataFrame([(i, f"{words} {i}", "en", "s", 9, 1.5, "x", True, 7, 2, "k", "m") for i in range(1, 7)],
                                 "doc_id long, text string, lang string, source string, n_chars long, score double, lang_pred string, kept boolean, keep_id long, size long, __id string, __letter string")
    for name, stage in C.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        assert all(r.score == 1.5 and r.lang_pred == "x" and r.keep_id == 7 and r.size == 2 for r in out.collect()), name
    assert C.STAGES[-1][1](spark, docs, SF).count() == 6


@pytest.mark.parametrize("rows", [[], [(1, None, None, None, None)], [(1, "one word here", None, "s", 3)]])
def test_stages_take_tiny_tables(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in C.STAGES:
        stage(spark, docs, SF).collect()
