import hashlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ripplerank.llm import bpe
from ripplerank.llm.queries import tokenizer_spec

tokenizers = pytest.importorskip("tokenizers")
public = pytest.importorskip("public_tokenizers")

ODD = [
    None, "", " ", "\n\t", "I'll say it's OK, don't <|startoftext|>you<|endoftext|>?", "İstanbul ΣΑΣ ὈΔΥΣΣΕΎΣ Σ",
    "é   x\u0085y", "12345 ½ ٣٤ Ⅷ", "日本語テキスト 👍🏽👍 ☃☃☃", "a" * 3000, "ab" * 2000 + "!" * 900, "'S'T'LL 'ſ",
    "<|endoftext|><|endoftext|>", "<|ENDOFTEXT|>", "\x00nul\x00", "\x00<|endoftext|>", "￾\U000e0001",
]


@pytest.fixture(scope="module")
def library():
    return tokenizers.Tokenizer.from_file(public.path("word_bpe_49k.json"))


@pytest.fixture(scope="module")
def vocabulary():
    return bpe.Vocabulary(tokenizer_spec())


def ours(v, text):
    return [i for w in v.words(text) for i in v.merge(w)]


@pytest.mark.parametrize("text", ODD[1:])
def test_odd_texts_as_the_library(library, vocabulary, text):
    assert ours(vocabulary, text) == library.encode(text, add_special_tokens=False).ids


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet=st.characters(codec="utf-8", categories=["L", "N", "P", "S", "Z", "M"], max_codepoint=0x24FF), max_size=40))
def test_any_text_as_the_library(text):
    library = tokenizers.Tokenizer.from_file(public.path("word_bpe_49k.json")) if not hasattr(test_any_text_as_the_library, "t") else test_any_text_as_the_library.t
    test_any_text_as_the_library.t = library
    v = getattr(test_any_text_as_the_library, "v", None) or bpe.Vocabulary(tokenizer_spec())
    test_any_text_as_the_library.v = v
    assert ours(v, text) == library.encode(text, add_special_tokens=False).ids


def test_lexicon_is_minimal_and_exact():
    words = sorted({f"{a}{b}ing".encode() for a in "abcdef" for b in "xyz"} | {b"a", b"ab", "é".encode()})
    entries = [(w, [i, i * 7]) for i, w in enumerate(words)]
    lexicon = bpe.Lexicon(bpe.compile_lexicon(entries))
    for w, ids in entries:
        assert np.frombuffer(lexicon.ids(w), "<u4").tolist() == ids
    for w in (b"", b"axin", b"axings", b"zz", b"abc"):
        assert lexicon.ids(w) is None
    assert lexicon.states < sum(map(len, words)) / 3
    assert bpe.Lexicon(bpe.compile_lexicon([])).ids(b"a") is None
    with pytest.raises(ValueError):
        bpe.compile_lexicon([(b"b", [1]), (b"a", [2])])


def test_operator_against_the_library(spark, library):
    given_docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    odd = spark.createDataFrame([(10_000 + i, t, 1) for i, t in enumerate(ODD)] + [(None, "null id", 2), (10_000, "again", 3)], "doc_id long, text string, ids int")
    docs = given_docs.unionByName(odd.drop("ids"))
    texts = sorted([(r.doc_id, r.text) for r in docs.collect()], key=str)
    rows = sorted([tuple(r) for r in bpe.encode_documents(docs, tokenizer_spec(), words=500).collect()], key=str)
    want = []
    for doc_id, text in texts:
        ids = library.encode(text or "", add_special_tokens=False).ids
        want.append((doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(),
                     hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert rows == sorted(want, key=str)
    back = bpe.decode_ids(bpe.encode_documents(odd, tokenizer_spec(), keep_ids=True, words=3), tokenizer_spec())
    for r in back.where("doc_id > 10000").collect():
        ids = library.encode(ODD[r.doc_id - 10_000] or "", add_special_tokens=False).ids
        assert r.decoded == library.decode(ids, skip_special_tokens=False)


def test_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert bpe.encode_documents(docs, tokenizer_spec()).count() == 0


def test_what_a_worker_remembers_stays_small():
    """Workers are kept between tasks and stages, and what they remember of words with them."""
    import struct
    import sys

    word, packed, string = "abcdefgh1234", struct.pack("<5I", *range(5)), "ab cd efg h1 234"
    entry = sys.getsizeof(word) + sys.getsizeof((packed, string)) + sys.getsizeof(packed) + sys.getsizeof(string) + 100  # and its place in the dict
    assert bpe.MEMO_WORDS * entry <= 48 << 20


def test_frequent_words_outlast_rare_ones(monkeypatch, tmp_path):
    """A worker's memo stays within its bytes and forgets what it has not met for long, not all at once."""
    spec = tokenizer_spec()
    vocabulary = bpe.Vocabulary(spec)
    (tmp_path / "lexicon").write_bytes(bpe.compile_lexicon([(b"of", vocabulary.merge("of"))]))
    monkeypatch.setattr(bpe.SparkFiles, "get", lambda name: str(tmp_path / name))
    monkeypatch.setattr(bpe, "MEMO_WORDS", 200)
    monkeypatch.setattr(bpe, "MEMO_BYTES", 200 * 200, raising=False)
    merged, merge = [], bpe.Vocabulary.merge
    monkeypatch.setattr(bpe.Vocabulary, "merge", lambda self, word: merged.append(word) or merge(self, word))
    encode = bpe._coder(spec, "lexicon")
    for i in range(0, 3000, 10):
        text = " ".join(["zweifellos of", *("q" + "".join("abcdefghij"[int(x)] for x in str(j)) for j in range(i, i + 10))])
        raw, decoded = encode(text)
        ids = [x for w in vocabulary.words(text) for x in merge(vocabulary, w)]
        assert raw == b"".join(x.to_bytes(4, "little") for x in ids) and decoded == " ".join(vocabulary.strings[x] for x in ids)
    assert merged.count("zweifellos") == 1
    bpe._coders.clear()
