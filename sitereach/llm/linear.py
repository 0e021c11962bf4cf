"""Hashed linear text classifiers trained with follow-the-regularised-leader updates.

Two feature makers share the learner: ``quality_features`` (word n-grams with a shape back-off, scaled
by the number of words) and ``toxic_features`` (word n-grams and skip-grams, present or not). A model is
a vector of 2**BITS weights; only weights that L1 leaves non-zero are kept, so what is broadcast is
bounded by the hash space whatever the corpus holds.

The learner reads a bounded sample of labelled rows (``sample``, a parameter; the rows with the smallest
hash of their doc_id), everything else covers all rows. A null or empty text has no features and gets
the score of the bias alone. A row with a null doc_id is scored, never held out and never learned from; of
several labels of one doc_id the largest counts, null labels count as none, and labels without a document are
left out. Repeated rows get equal scores, and each is learned from while the sample lasts. With no labelled row
at all every score is 0.5; an empty table gives an empty one. Further columns are not read by ``score`` and are
kept by ``kept``.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit
from .textkit import U64, mix

BITS = 18
#: Labelled rows that a model is fitted on at most.
SAMPLE = 6000
#: Bytes of the word stems that back off rare words in the toxicity features.
STEMS = (5, 7)


def _bucket(h: np.ndarray, kind: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return (mix(h + U64(kind) * U64(0xA24BAED4963EE407)) >> U64(64 - BITS)).astype(np.int64)


def _pairs(words: textkit.Words, value: np.ndarray, gap: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each two values that stand ``gap`` words apart in a row, and the row."""
    a, b = value[:-gap], value[gap:]
    same = words.row[:-gap] == words.row[gap:]
    with np.errstate(over="ignore"):
        return mix(a * U64(0x9FB21C651E98DF25) + b)[same], words.row[:-gap][same]


def _shapes(raw: np.ndarray, words: textkit.Words) -> np.ndarray:
    """A small code of what a word looks like: upper-case share, marks other than letters and digits, length."""
    letters = np.zeros(256, np.int64)
    letters[65:91] = 1
    upper = np.concatenate([[0], np.cumsum(letters[raw])])
    mark = np.concatenate([[0], np.cumsum(~textkit._ALNUM[raw])])
    n = words.end - words.start
    up, marks = upper[words.end] - upper[words.start], mark[words.end] - mark[words.start]
    code = np.minimum(up, 2) * 3 + (2 * up > n)
    return (code * 5 + np.minimum(marks, 4)) * 8 + np.minimum(n, 28) // 4


def quality_features(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bucket, row, value): hashed words and word pairs, with their shapes as back-off for rare words, over the word count."""
    words = textkit.Words(raw, offsets)
    shape = _shapes(raw, words).astype(U64)
    again = np.zeros(len(shape), U64)
    again[1:] = words.hash[1:] == words.hash[:-1]
    look = shape * U64(2) + again
    h2, r2 = _pairs(words, words.hash, 1)
    s2, q2 = _pairs(words, look, 1)
    bucket = np.concatenate([_bucket(words.hash, 1), _bucket(look, 2), _bucket(h2, 3), _bucket(s2, 4)])
    row = np.concatenate([words.row, words.row, r2, q2])
    share = 8.0 / np.maximum(words.counts(), 1)
    return bucket, row, share[row]


def toxic_features(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bucket, row, 1): hashed words, word stems, word pairs and one-word skip-grams that a text holds."""
    words = textkit.Words(raw, offsets, "mark")
    h2, r2 = _pairs(words, words.hash, 1)
    h3, r3 = _pairs(words, words.hash, 2)
    bucket = np.concatenate([_bucket(words.hash, 5), _bucket(h2, 6), _bucket(h3, 7), *(_bucket(words.stems(n), 8 + n) for n in STEMS if len(words.hash))])
    row = np.concatenate([words.row, r2, r3, *(words.row for _ in STEMS if len(words.hash))])
    key = np.unique(row.astype(np.int64) << BITS | bucket)
    return key & ((1 << BITS) - 1), key >> BITS, np.ones(len(key))


@dataclass
class Model:
    """index: buckets with a weight, ascending; weight: theirs; bias."""

    index: np.ndarray
    weight: np.ndarray
    bias: float
    features: Callable

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << BITS)
        out[self.index] = self.weight
        return out


def _give_back() -> None:
    """Return freed memory to the system: the driver goes on for long after the fit."""
    gc.collect()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library looks after itself


def train(texts: list[str], labels: np.ndarray, features: Callable, alpha: float, beta: float, l1: float, l2: float, passes: int) -> Model:
    """FTRL-proximal with a rate for each coordinate; rows in the given order, ``passes`` times."""
    z, n = np.zeros((1 << BITS) + 1), np.zeros((1 << BITS) + 1)
    rows = []
    for text in texts:
        raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
        bucket, _, value = features(raw, np.array([0, len(raw)], np.int64))
        at, where = np.unique(bucket, return_inverse=True)
        rows.append((np.append(at, 1 << BITS).astype(np.int32), np.append(np.bincount(where, value, len(at)), 1.0)))

    def weights(at: np.ndarray) -> np.ndarray:
        zi = z[at]
        w = (np.sign(zi) * l1 - zi) / ((beta + np.sqrt(n[at])) / alpha + l2)
        return np.where(np.abs(zi) <= l1, 0.0, w)

    for _ in range(passes):
        for (at, value), y in zip(rows, labels, strict=True):
            w = weights(at)
            p = 1.0 / (1.0 + np.exp(-np.clip(w @ value, -35, 35)))
            g = (p - y) * value
            step = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / alpha
            z[at] += g - step * w
            n[at] += g * g
    w = weights(np.arange((1 << BITS) + 1))
    index = np.flatnonzero(w[:-1])
    del rows
    _give_back()
    return Model(index, w[index], float(w[-1]), features)


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, mod: int, held: int, sample: int) -> tuple[list[str], np.ndarray]:
    """At most ``sample`` labelled rows that are not held out, those whose hashed doc_id is smallest."""
    ids = labels.select("doc_id", F.col(label).cast("int").alias("y")).where("doc_id is not null and y is not null").where(held_out(mod, held) == F.lit(False))
    ids = ids.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    # the sample is bounded by its parameter, so this side may be broadcast
    rows = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", "text").limit(sample).collect()
    return [r["text"] for r in rows], np.array([float(r["y"]) for r in rows])


def held_out(mod: int, held: int):
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % mod == held, F.lit(False))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and score of every whole text: one pass, no shuffle; the weights travel with the task."""
    shared = docs.sparkSession.sparkContext.broadcast((model.index, model.weight, model.bias))
    features = model.features

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, weight, bias = shared.value
        dense = Model(index, weight, bias, features).dense()
        for part in textkit.slices(batches, "text"):
            bucket, row, value = features(*textkit.text_bytes(part.column(1)))
            total = bias + np.bincount(row, dense[bucket] * value, part.num_rows)
            yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array(1.0 / (1.0 + np.exp(-np.clip(total, -35, 35))))], names=["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, score double")


def kept(docs: DataFrame, model: Model, least: float) -> DataFrame:
    """The rows that score ``least`` or more, whole and with all their columns, in one pass."""
    shared = docs.sparkSession.sparkContext.broadcast((model.index, model.weight, model.bias))
    features, bound = model.features, float(np.log(least / (1 - least)))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, weight, bias = shared.value
        dense = Model(index, weight, bias, features).dense()
        for part in textkit.slices(batches, "text"):
            bucket, row, value = features(*textkit.text_bytes(part.column(part.schema.get_field_index("text"))))
            yield part.filter(pa.array(bias + np.bincount(row, dense[bucket] * value, part.num_rows) >= bound))

    return docs.mapInArrow(work, docs.schema)


QUALITY = {"alpha": 0.3, "beta": 1.0, "l1": 0.02, "l2": 0.1, "passes": 4}
TOXIC = {"alpha": 0.5, "beta": 1.0, "l1": 10.0, "l2": 0.1, "passes": 6}


def fit_quality(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    return train(*labelled_sample(docs, labels, "quality", 3, 1, sample), quality_features, **QUALITY)


def fit_toxic(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    return train(*labelled_sample(docs, labels, "toxic", 4, 2, sample), toxic_features, **TOXIC)


def _contract(scored: DataFrame, mod: int, held: int, least: float) -> DataFrame:
    return scored.select("doc_id", held_out(mod, held).alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))


def _tables(spark, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")


def op4_quality(spark, sf_dir: str) -> DataFrame:
    docs, labels = _tables(spark, sf_dir)
    return _contract(score(docs, fit_quality(docs, labels)), 3, 1, 0.5)


def op5_toxicity(spark, sf_dir: str) -> DataFrame:
    docs, labels = _tables(spark, sf_dir)
    return _contract(score(docs, fit_toxic(docs, labels)), 4, 2, 0.3)
