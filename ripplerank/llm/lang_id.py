"""Language identification by error-correcting output codes over byte n-grams."""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name
from .textnum import mix, slices

#: Bound of the training sample: labelled texts expected per language.
SAMPLE = 2000
#: Hashed n-gram features per order are folded into this many cells.
CELLS = 1 << 15
ORDERS = (1, 2, 3)
#: Tasks that learn.
MOST_TASKS = 64
UNKNOWN = "und"
#: A best codeword ahead of the next by less than this share of certainty is flagged.
AMBIGUOUS = 0.6

# Letters as they are counted: A-Z folded, runs of other ASCII as one space each.
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[:128] = 32
_FOLD[97:123] = np.arange(97, 123)
_FOLD[65:91] = np.arange(97, 123)


def _features(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each order: (cells, text of each n-gram). N-grams of blanks alone are left out."""
    text = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    folded = _FOLD[data].astype(np.uint64)
    for n in ORDERS:
        m = len(folded) - n + 1
        if m <= 0:
            return
        code = folded[:m].copy()
        for i in range(1, n):
            code = (code << np.uint64(8)) | folded[i : i + m]
        blank = int.from_bytes(b" " * n, "big")
        ok = (text[:m] == text[n - 1 :]) & (code != blank)
        yield (mix(code[ok] + np.uint64(n << 40)) >> np.uint64(49)).astype(np.int64), text[:m][ok], ok


def codewords(n: int, seed: int = 5) -> np.ndarray:
    """A row of -1/+1 bits per language.

    Up to five languages take all distinct two-way splits; more take the best of several
    random codes of 10 log2 n bits by least distance between rows.
    """
    if n <= 1:
        return np.ones((n, 1), np.int8)
    if n <= 5:
        splits = [s for s in itertools.product((1, -1), repeat=n) if s[0] == 1 and -1 in s]
        return np.array(splits, np.int8).T
    rng, best = np.random.default_rng(seed), None
    for _ in range(50):
        code = rng.choice(np.array([-1, 1], np.int8), (n, int(np.ceil(10 * np.log2(n)))))
        code = code[:, np.abs(code.sum(0)) < n]
        least = min(int((a != b).sum()) for a, b in itertools.combinations(code, 2))
        if best is None or least > best[0]:
            best = least, code
    return best[1]


@dataclass
class LanguageModel:
    languages: list[str]
    code: np.ndarray  # languages x bits
    weights: np.ndarray  # cells x bits: log odds of each bit
    trust: np.ndarray  # loss weight of each bit
    scale: np.ndarray  # of each bit's margin

    def margins(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Mean log odds of each bit for each text, in units of the training texts' mean margin."""
        n = len(offsets) - 1
        total, count = np.zeros((n, self.code.shape[1])), np.zeros(n)
        for cells, text, _ in _features(data, offsets):
            seen = np.bincount(text, minlength=n)
            begin = np.cumsum(seen) - seen
            held = np.flatnonzero(seen)
            if len(held):
                for b in range(self.code.shape[1]):
                    total[held, b] += np.add.reduceat(self.weights[:, b][cells], begin[held])
            count += seen
        return total / np.maximum(count, 1)[:, None] / self.scale

    def decode(self, margins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the codeword of least weighted logistic loss, and its certainty against all others."""
        loss = np.stack([(np.logaddexp(0, -2 * margins * row) * self.trust).sum(1) for row in self.code], 1)
        odds = np.exp(loss.min(1, keepdims=True) - loss)
        best = loss.argmin(1)
        return best, 1 / odds.sum(1)


def _letters(text: Column) -> Column:
    return F.coalesce(text.rlike(r"\p{L}"), F.lit(False))


def fit(labelled: DataFrame, sample: int = SAMPLE) -> LanguageModel:
    """Learn from rows (doc_id, text, lang) with non-null lang.

    About `sample` texts of each language are drawn by a hash of doc_id, in one pass after
    a count; that bounds training whatever the table's size. Executors turn whole texts into
    n-gram counts per language, and only those fixed-size counts reach the driver. Each bit
    is a two-class multinomial model with equal priors; a bit's loss weight is its
    accuracy on the sampled texts. No labelled rows give a model without languages.
    """
    rows = labelled.where(F.col("lang").isNotNull() & _letters(F.col("text")))
    counts = {r[0]: r[1] for r in rows.groupBy("lang").count().collect()}
    languages = sorted(counts)
    if not languages:
        return LanguageModel([], np.ones((0, 1), np.int8), np.zeros((CELLS, 1)), np.ones(1), np.ones(1))
    number = {x: i for i, x in enumerate(languages)}
    chance = F.element_at(F.create_map(*[F.lit(v) for x in languages for v in (x, min(1.0, sample / counts[x]))]), F.col("lang"))
    drawn = rows.where(F.pmod(F.xxhash64(F.lit("train"), "doc_id"), F.lit(1 << 30)) < chance * (1 << 30)).select("lang", "text", F.xxhash64("doc_id", "text").alias("deal"))
    # Each task sends one table of counts to the driver, so few tasks share the bounded sample.
    tasks = max(8, min(MOST_TASKS, labelled.sparkSession.sparkContext.defaultParallelism))
    spread = drawn.repartition(tasks, "deal").select("lang", "text")

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams = np.zeros((len(languages), CELLS), np.int64)
        for batch in batches:
            for part, data, offsets in slices(batch, "text"):
                owner = np.array([number[x] for x in part.column("lang").to_pylist()])
                for cells, text, _ in _features(data, offsets):
                    np.add.at(grams, (owner[text], cells), 1)
        yield pa.RecordBatch.from_arrays(
            [pa.array(languages, pa.string()), pa.array([g.astype("<i8").tobytes() for g in grams], pa.binary())], ["lang", "grams"]
        )

    total = np.zeros((len(languages), CELLS))
    for lang, grams in spread.mapInArrow(tally, "lang string, grams binary").toLocalIterator():
        total[number[lang]] += np.frombuffer(grams, "<i8")
    code = codewords(len(languages))
    share = (total + 0.5) / (total + 0.5).sum(1, keepdims=True)
    weights = np.zeros((CELLS, code.shape[1]))
    for b in range(code.shape[1]):
        yes, no = share[code[:, b] > 0], share[code[:, b] < 0]
        if len(yes) and len(no):
            weights[:, b] = np.log(yes.mean(0)) - np.log(no.mean(0))
    model = LanguageModel(languages, code, weights, np.ones(code.shape[1]), np.ones(code.shape[1]))

    def rate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        right, size, n = np.zeros(code.shape[1]), np.zeros(code.shape[1]), 0
        for batch in batches:
            for part, data, offsets in slices(batch, "text"):
                truth = code[[number[x] for x in part.column("lang").to_pylist()]]
                m = model.margins(data, offsets)
                right += (m * truth > 0).sum(0)
                size += np.abs(m).sum(0)
                n += len(m)
        yield pa.RecordBatch.from_arrays([pa.array([right]), pa.array([size]), pa.array([n])], ["rights", "sizes", "n"])

    checked = spread.mapInArrow(rate, "rights array<double>, sizes array<double>, n bigint").collect()
    n = max(1, sum(r.n for r in checked))
    model.trust = np.maximum(np.sum([r.rights for r in checked], 0) / n, 0.5)
    model.scale = np.maximum(np.sum([r.sizes for r in checked], 0) / n, 1e-9)
    return model


def identify(docs: DataFrame, model: LanguageModel, ambiguous: float = AMBIGUOUS) -> DataFrame:
    """Language of every whole text, from the text alone: all columns of `docs`, lang_pred, score, is_ambiguous.

    Null texts and texts without a letter are `und` with score 0, as is everything under a
    model without languages. `score` is the certainty of the loss-weighted decoding, and
    texts below `ambiguous` are flagged. Columns of `docs` that bear a result's name give way to it. Rows stay one to one; no shuffle.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop("lang_pred", "score", "is_ambiguous")
    fields = [*docs.schema.fieldNames()]
    letter_name = free_name(docs, "__letter")
    marked = docs.withColumn(letter_name, _letters(F.col("text")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            langs, scores = [], []
            for part, data, offsets in slices(batch, "text"):
                letter = part.column(letter_name).to_pylist()
                if m.languages:
                    best, sure = m.decode(m.margins(data, offsets))
                    langs += [m.languages[i] if ok else UNKNOWN for i, ok in zip(best, letter)]
                    scores += [float(s) if ok else 0.0 for s, ok in zip(sure, letter)]
                else:
                    langs += [UNKNOWN] * len(letter)
                    scores += [0.0] * len(letter)
            yield pa.RecordBatch.from_arrays(
                [batch.column(i) for i in range(len(fields))]
                + [pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array([s < ambiguous for s in scores], pa.bool_())],
                [*fields, "lang_pred", "score", "is_ambiguous"],
            )

    from pyspark.sql import types as T

    schema = T.StructType([*docs.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("is_ambiguous", T.BooleanType())])
    return marked.mapInArrow(run, schema)


def train_split(docs: DataFrame) -> DataFrame:
    """The rows the contract lets a model learn from: crc32 of doc_id as text mod 3 is not 1, lang not null."""
    return docs.where(F.col("lang").isNotNull() & ~held_out()).select("doc_id", "text", "lang")


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))
