"""BPE encoding and decoding through a memory-mapped minimal acyclic lexicon.

The most frequent words of the corpus are compiled with their ids into a
shared-suffix automaton. Each state keeps how many words it accepts, so that the path of
a word also numbers it, and its ids are found by that number. The file is laid out for
memory-mapping; it reaches executors as a Spark file. Words that it lacks are merged
exactly by rank. Which words are compiled only changes speed, never a result.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import mmap
import re
import struct
import unicodedata
from collections import Counter
from collections.abc import Iterable, Iterator
from sys import getsizeof

import numpy as np
import pyarrow as pa
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, shared_path

#: Words compiled into the lexicon: a documented bound on its size (about 2 MB), not on the text.
LEXICON_WORDS = 16384
#: Distinct words that a task counts before it hands them on.
MEMO_WORDS = 100_000
#: Bytes of words and ids that a worker remembers (in two halves, of which the older is forgotten), and what a place in a dict takes.
MEMO_BYTES, PLACE_BYTES = 48 << 20, 100
_WORD = 40

# ---------------------------------------------------------------- the tokenizer's definition


class Vocabulary:
    """What a tokenizer file defines: ids, merge ranks, pre-tokenising pattern and special strings."""

    def __init__(self, spec: str):
        d = json.loads(spec)
        model, split = d["model"], d["pre_tokenizer"]["pretokenizers"][0]
        kinds = [n["type"] for n in d["normalizer"]["normalizers"]]
        if model["type"] != "BPE" or kinds != ["NFC", "Replace", "Lowercase"] or not split["invert"] or d["decoder"]:
            raise ValueError("this tokenizer file defines steps that are not implemented")
        ids: dict[str, int] = model["vocab"]
        pairs = (m if isinstance(m, list) else m.split(" ") for m in model["merges"])
        self.end = model["end_of_word_suffix"] or ""
        # A pair of ids is one integer; merges[rank] is the id that it becomes.
        self.ranks: dict[int, int] = {}
        self.merges: list[int] = []
        for a, b in pairs:
            self.ranks[ids[a] << 20 | ids[b]] = len(self.merges)
            self.merges.append(ids[a + b])
        self.special = {t["content"]: t["id"] for t in d["added_tokens"]}
        self.strings = {i: s for s, i in [*ids.items(), *self.special.items()]}
        self.find_any = regex.compile(split["pattern"]["Regex"]).findall
        self.find_latin = _latin(split["pattern"]["Regex"])
        self.cut = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")").split
        letters = _byte_letters()
        if missing := [x for x in letters if x not in ids or x + self.end not in ids]:
            raise ValueError(f"no ids for {missing}")
        self.inner, self.last = [ids[x] for x in letters], [ids[x + self.end] for x in letters]

    def find(self, text: str) -> list[str]:
        """Words of a normalised text."""
        if self.find_latin:
            try:
                text.encode("latin-1")
                return self.find_latin(text)
            except UnicodeEncodeError:
                pass
        return self.find_any(text)

    def words(self, text: str) -> list[str]:
        """Normalised words of a text between special strings; a special string stands for itself, marked by NUL."""
        if not any(s in text for s in self.special):
            return self.find(_normal(text))
        out: list[str] = []
        for part in self.cut(text):
            out += ["\0" + part] if part in self.special else self.find(_normal(part))
        return out

    def merge(self, word: str) -> list[int]:
        """Ids of one word by exact merging: the pair of least rank first, the leftmost among equals."""
        if word[0] == "\0" and word[1:] in self.special:
            return [self.special[word[1:]]]
        raw = word.encode("utf-8")
        parts = [self.inner[b] for b in raw]
        parts[-1] = self.last[raw[-1]]
        return self._merge_long(parts) if len(parts) > 64 else self._merge_short(parts)

    def _merge_short(self, parts: list[int]) -> list[int]:
        rank, none = self.ranks.get, len(self.merges)
        costs = [rank(a << 20 | b, none) for a, b in zip(parts, parts[1:])]
        while costs:
            best = min(costs)
            if best == none:
                break
            i = costs.index(best)
            parts[i] = self.merges[best]
            del parts[i + 1], costs[i]
            if i:
                costs[i - 1] = rank(parts[i - 1] << 20 | parts[i], none)
            if i < len(costs):
                costs[i] = rank(parts[i] << 20 | parts[i + 1], none)
        return parts

    def _merge_long(self, parts: list[int]) -> list[int]:
        """The same with a heap over a linked list, so that a long word costs n log n."""
        n, rank = len(parts), self.ranks.get
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, a, b) for i, (a, b) in enumerate(zip(parts, parts[1:])) if (r := rank(a << 20 | b)) is not None]
        heapq.heapify(heap)
        while heap:
            best, i, a, b = heapq.heappop(heap)
            j = after[i]
            if parts[i] != a or j >= n or parts[j] != b:
                continue
            parts[i], parts[j] = self.merges[best], -1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (r := rank(parts[i] << 20 | parts[k])) is not None:
                    heapq.heappush(heap, (r, i, parts[i], parts[k]))
            if (h := before[i]) >= 0 and (r := rank(parts[h] << 20 | parts[i])) is not None:
                heapq.heappush(heap, (r, h, parts[h], parts[i]))
        return [p for p in parts if p >= 0]


def _latin(pattern: str):
    """A faster equal of the one pattern in use, for texts within Latin-1 (letters spelled out); else None."""
    if pattern != r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+":
        return None
    letters, digits = "A-Za-z\u00aa\u00b5\u00ba\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff", "0-9\u00b2\u00b3\u00b9\u00bc-\u00be"
    space = "\t-\r \u0085\u00a0"
    return re.compile(f"[{letters}]+|'(?:s|t|re|ve|m|ll|d)|[{digits}]|[^{letters}{digits}{space}]+").findall


def _byte_letters() -> list[str]:
    """The printable letter of each byte: itself where printable, else the next free one from U+0100."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def _normal(text: str) -> str:
    text = unicodedata.normalize("NFC", text)
    # str.lower() alone would look at a sigma's neighbours, which the library does not.
    return text.lower() if "Σ" not in text else "".join(c.lower() for c in text)


# ---------------------------------------------------------------- the lexicon automaton


def compile_lexicon(entries: Iterable[tuple[bytes, list[int]]]) -> bytes:
    """Minimal acyclic automaton of sorted distinct words with id outputs, as one mappable block.

    Built incrementally: once a word leaves a branch, the branch's states are replaced by
    registered states with the same future, so suffixes are shared.
    """
    register: dict[tuple, int] = {}
    done: list[tuple[bool, tuple[tuple[int, int], ...]]] = []
    path: list[tuple[bool, list[tuple[int, int]], int]] = [[False, [], -1]]  # accepting, arcs, label into it

    def freeze(depth: int) -> None:
        while len(path) > depth:
            accepting, arcs, label = path.pop()
            key = (accepting, tuple(arcs))
            state = register.setdefault(key, len(done))
            if state == len(done):
                done.append(key)
            path[-1][1].append((label, state))

    last, outputs = b"", []
    for word, ids in entries:
        if outputs and word <= last:
            raise ValueError("entries must be sorted and distinct")
        common = next((i for i, (a, b) in enumerate(zip(word, last)) if a != b), min(len(word), len(last)))
        freeze(common + 1)
        for b in word[common:]:
            path.append([False, [], b])
        path[-1][0] = True
        last = word
        outputs.append(ids)
    freeze(1)
    root = len(done)
    done.append((path[0][0], tuple(path[0][1])))

    accepted = [0] * len(done)
    firsts, labels, targets, skips = [0], bytearray(), [], []
    for s, (accepting, arcs) in enumerate(done):  # targets precede their sources
        total = int(accepting)
        for label, t in arcs:
            labels.append(label)
            targets.append(t)
            skips.append(total)
            total += accepted[t]
        accepted[s] = total
        firsts.append(len(labels))
    bounds = np.cumsum([0, *map(len, outputs)], dtype=np.uint32)
    parts = [
        np.array(firsts, np.uint32), np.array(targets, np.uint32), np.array(skips, np.uint32),
        bounds, np.array([i for ids in outputs for i in ids], np.uint32),
    ]
    head = struct.pack("<7I", root, len(done), *map(len, parts))
    final = bytes(int(a) for a, _ in done)
    return head + b"".join(p.astype("<u4").tobytes() for p in parts) + bytes(labels) + final


class Lexicon:
    """Lookups in a compiled block, read in place from a memory map."""

    def __init__(self, block):
        self.block = block
        self.root, states, *sizes = struct.unpack_from("<7I", block, 0)
        at, views = 28, []
        for n in sizes:
            views.append(memoryview(block)[at : at + 4 * n].cast("I"))
            at += 4 * n
        self.first, self.target, self.skip, self.bound, self.out = views
        self.labels, self.final = at, at + sizes[1]
        self.states = states

    def ids(self, word: bytes) -> bytes | None:
        """The word's ids as little-endian bytes, or None for a word that is not compiled."""
        s, number, block = self.root, 0, self.block
        for b in word:
            at = block.find(b.to_bytes(1, "little"), self.labels + self.first[s], self.labels + self.first[s + 1])
            if at < 0:
                return None
            at -= self.labels
            number += self.skip[at]
            s = self.target[at]
        if not block[self.final + s]:
            return None
        return self.out[self.bound[number] : self.bound[number + 1]].tobytes()


# ---------------------------------------------------------------- Spark


def word_counts(docs: DataFrame, spec: str) -> DataFrame:
    """Counts of all words of all texts: word, n. Tasks count first, so the shuffle carries distinct words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, counts = Vocabulary(spec), Counter()

        def out() -> pa.RecordBatch:
            done = pa.RecordBatch.from_arrays([pa.array(list(counts), pa.string()), pa.array(list(counts.values()), pa.int64())], ["word", "n"])
            counts.clear()
            return done

        for batch in batches:
            for text in batch.column(0).to_pylist():
                if text:
                    counts.update(vocabulary.words(text))
            if len(counts) > MEMO_WORDS:
                yield out()
        if counts:
            yield out()

    return docs.select("text").mapInArrow(run, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n"))


def frequent_words(counts: DataFrame, most: int) -> list[str]:
    """Words at or above the least count, on a scale of eighths of powers of two, that at most `most` words reach."""
    plain = cut(counts.where((F.length("word") <= _WORD) & ~F.col("word").startswith("\0")), "words").withColumn(
        "scale", F.floor(8 * F.log2("n") + 1e-9)
    )
    kept, least = 0, None
    for scale, n in sorted(plain.groupBy("scale").count().collect(), reverse=True):  # some hundreds of rows
        if kept + n > most:
            break
        kept, least = kept + n, scale
    return [] if least is None else [r[0] for r in plain.where(F.col("scale") >= least).select("word").collect()]


def ship_lexicon(spark: SparkSession, counts: DataFrame, spec: str, words: int = LEXICON_WORDS) -> str:
    """Compile the most frequent words and hand the file to all executors; returns its Spark file name.

    At most `words` short rows reach the driver. The file lies in the shared folder,
    where executors that join later fetch it too.
    """
    vocabulary = Vocabulary(spec)
    top = frequent_words(counts, words)
    entries = sorted((w.encode("utf-8"), vocabulary.merge(w)) for w in top)
    block = compile_lexicon(entries)
    name = f"lexicon-{hashlib.sha256(block).hexdigest()[:24]}.bin"
    path = f"{shared_path(spark, 'lexicon')}/{name}"
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    stream = hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).create(hadoop, True)
    try:
        stream.write(bytearray(block))
    finally:
        stream.close()
    if not any(f.endswith("/" + name) for f in spark.sparkContext.listFiles):
        spark.sparkContext.addFile(path)
    return name


_coders: dict[tuple[int, str], object] = {}


def _coder(spec: str, name: str):
    """The worker's encoder for a lexicon, kept between tasks: it holds the memo of words seen."""
    if (hash(spec), name) in _coders:
        return _coders[hash(spec), name]
    vocabulary = Vocabulary(spec)
    strings = vocabulary.strings
    with open(SparkFiles.get(name), "rb") as f:
        lexicon = Lexicon(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ))
    memo: dict[str, bytes] = {}
    old: dict[str, bytes] = {}

    size = 0

    def look(word: str) -> bytes:
        nonlocal memo, old, size
        packed = old.get(word) or lexicon.ids(word.encode("utf-8"))
        if packed is None:
            ids = vocabulary.merge(word)
            packed = struct.pack(f"<{len(ids)}I", *ids)
        size += getsizeof(word) + getsizeof(packed) + PLACE_BYTES
        if size > MEMO_BYTES // 2:  # words met again come over from the older half
            old, memo, size = memo, {}, 0
        memo[word] = packed
        return packed

    def encode(text: str | None) -> tuple[bytes, str]:
        if not text:
            return b"", ""
        raw = b"".join([memo.get(w) or look(w) for w in vocabulary.words(text)])
        return raw, " ".join(map(strings.__getitem__, np.frombuffer(raw, "<u4").tolist()))

    _coders.clear()
    _coders[hash(spec), name] = encode
    return encode


def encode_documents(docs: DataFrame, spec: str, keep_ids: bool = False, words: int = LEXICON_WORDS) -> DataFrame:
    """Encode and decode every whole text: doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids with `keep_ids`).

    `spec` is the text of a tokenizer file, read once by the driver. Special strings in a
    text become their own ids, as the library has it. Null and empty texts give no ids.
    Rows stay one to one, repeated rows and null ids included; other columns are not read.
    """
    spark = docs.sparkSession
    name = ship_lexicon(spark, word_counts(docs, spec), spec, words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _coder(spec, name)
        for batch in batches:
            counts, ids, digests, decoded = [], [], [], []
            for text in batch.column("text"):
                raw, string = encode(text.as_py())
                counts.append(len(raw) // 4)
                digests.append(hashlib.sha256(raw).hexdigest())
                decoded.append(hashlib.sha256(string.encode("utf-8")).hexdigest())
                if keep_ids:
                    ids.append(np.frombuffer(raw, "<u4").astype(np.int32))
            columns = [batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(digests, pa.string()), pa.array(decoded, pa.string())]
            yield pa.RecordBatch.from_arrays(
                columns + ([pa.array(ids, pa.list_(pa.int32()))] if keep_ids else []),
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] + ["ids"] * keep_ids,
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(
        run, f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids
    )


def decode_ids(encoded: DataFrame, spec: str) -> DataFrame:
    """Texts of the `ids` column: doc_id, decoded. Special ids keep their strings; null ids decode to the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        strings = Vocabulary(spec).strings
        for batch in batches:
            texts = [" ".join(strings[i] for i in row or ()) for row in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "decoded"])

    kind = encoded.schema["doc_id"].dataType.simpleString()
    return encoded.select("doc_id", "ids").mapInArrow(run, f"doc_id {kind}, decoded string")
