"""Toxicity by FTRL-proximal logistic regression over hashed word n-grams.

Features of a text: its words, neighbouring pairs, and pairs with one word skipped, each
hashed to one of 2^BITS coordinates; a feature is there or not, however often. Words are
lower-cased and lose ASCII punctuation at both ends. The regression keeps a learning
rate per coordinate and an L1 bound, so few weights are not zero: they go to the tasks with
the scoring function, 12 bytes each.

The model is fitted on a bounded sample of labelled rows, `SAMPLE` at most: those
first by hash of their doc_id, shown in that order `EPOCHS` times to one task. Only rows whose
crc32 of the doc_id as text leaves a remainder mod 5 are ever learnt from. Scoring covers
all rows and whole texts, and sees nothing but the text. Features that fewer than `MIN_TEXTS`
of the sampled texts have are not learnt: they get no weight.

Defined results: null and empty texts have no features and get the score of the intercept; several
labels of one doc_id count as toxic if one of them is; null labels and ids teach nothing; a null
doc_id is not held out; without labels every score is 0.5 and predicted 1; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from string import punctuation

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rankjoin.llm.common import releasing, runs, table

BITS = 20
SAMPLE = 16_000
EPOCHS = 8
#: Features of fewer sampled texts than this are left out.
MIN_TEXTS = 5
FOLDS = 5
RATE, SMOOTH, L1, L2 = 0.6, 1.0, 12.0, 0.0
BATCH_CHARS = 3_000_000
WORDS = 400_000


class _Hashes(dict):
    """Hash of a word, found once."""

    def __missing__(self, word: str) -> int:
        h = self[word] = xxhash.xxh64_intdigest(word.strip(punctuation) or word)
        return h


class Featurizer:
    """Coordinates of the features of texts."""

    def __init__(self, bits: int = BITS) -> None:
        self.shift, self.known = np.uint64(64 - bits), _Hashes()

    def _of(self, *parts: np.ndarray) -> np.ndarray:
        h = np.full(len(parts[0]), np.uint64(len(parts)))
        for p in parts:
            h = (h ^ p) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        return (h * np.uint64(0xBF58476D1CE4E5B9)) >> self.shift

    def __call__(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(text number, coordinate) of every feature occurrence."""
        if len(self.known) > WORDS:
            self.known.clear()
        words = [x.lower().split() for x in texts]
        sizes = [len(w) for w in words]
        owner = np.repeat(np.arange(len(texts)), sizes)
        h = np.fromiter(map(self.known.__getitem__, (w for x in words for w in x)), np.uint64, len(owner))
        who, what = [owner], [self._of(h)]
        for gap in (1, 2):
            same = owner[gap:] == owner[:-gap] if len(owner) > gap else np.zeros(0, bool)
            who.append(owner[:-gap][same] if len(owner) > gap else owner[:0])
            what.append(self._of(h[:-gap][same], h[gap:][same] + np.uint64(gap)) if len(owner) > gap else what[0][:0])
        return np.concatenate(who), np.concatenate(what).astype(np.int64)


def fit(examples: list[tuple[int, np.ndarray]], *, bits: int = BITS, epochs: int = EPOCHS, rate: float = RATE, smooth: float = SMOOTH, l1: float = L1, l2: float = L2) -> tuple[np.ndarray, np.ndarray]:
    """(coordinates, weights) that are not zero; coordinate 2^bits is the intercept, which L1 leaves alone."""
    size = 1 << bits
    z, n = np.zeros(size + 1), np.zeros(size + 1)
    bound = np.full(size + 1, l1)
    bound[size] = 0.0

    def weights(at) -> np.ndarray:
        zs = z[at]
        return np.where(np.abs(zs) <= bound[at], 0.0, -(zs - np.sign(zs) * bound[at]) / ((smooth + np.sqrt(n[at])) / rate + l2))

    for _ in range(epochs):
        for label, features in examples:
            at = np.append(features, size)
            w = weights(at)
            p = 1 / (1 + np.exp(-np.clip(w.sum(), -35, 35)))
            g = p - label
            step = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / rate
            z[at] += g - step * w
            n[at] += g * g
    w = weights(slice(None))
    at = np.flatnonzero(w)
    return at, w[at]


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % FOLDS == 0, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, *, sample: int = SAMPLE) -> tuple[np.ndarray, np.ndarray]:
    """Fit on the labelled rows of docs (doc_id, text) outside the held-out fold."""
    known = labels.where("doc_id is not null and toxic is not null").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("label"))
    order = F.xxhash64("doc_id")
    known = known.orderBy(order, "doc_id").limit(sample).withColumnRenamed("doc_id", "_id")
    rows = docs.select("doc_id", "text").join(F.broadcast(known), F.col("doc_id") == F.col("_id")).select(order.alias("at"), "doc_id", "label", "text")

    @releasing
    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Featurizer()
        for batch in batches:
            found = [np.unique(make([x or ""])[1]).astype(np.int32) for x in batch.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(found, pa.list_(pa.int32()))], names=["at", "doc_id", "label", "features"])

    schema = T.StructType([T.StructField("at", T.LongType()), docs.schema["doc_id"], T.StructField("label", T.IntegerType()), T.StructField("features", T.ArrayType(T.IntegerType()))])

    @releasing
    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        examples = [(label, np.array(f, np.int64)) for batch in batches for label, f in zip(batch.column(2).to_pylist(), (x.values.to_numpy() for x in batch.column(3)), strict=True)]
        if examples:
            often = np.bincount(np.concatenate([f for _, f in examples]), minlength=1 << BITS) >= MIN_TEXTS
            examples = [(label, f[often[f]]) for label, f in examples]
        at, w = fit(examples) if examples else (np.zeros(0, np.int64), np.zeros(0))
        yield pa.RecordBatch.from_pydict({"at": pa.array(at, pa.int64()), "w": pa.array(w, pa.float64())})

    one = rows.mapInArrow(features, schema).repartition(1).sortWithinPartitions("at", "doc_id")  # `sample` rows at most
    got = one.mapInArrow(learn, "at long, w double").collect()  # weights that are not zero: 2^BITS at most
    return np.array([r.at for r in got], np.int64), np.array([r.w for r in got])


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """doc_id and score of every row of docs (doc_id, text)."""
    at, w = model

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = 1 << BITS
        table_, make = np.zeros(size + 1, np.float32), Featurizer()
        table_[at] = w
        for batch in batches:
            texts = batch.column(1)
            for a, b in runs(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False), BATCH_CHARS):
                who, what = make([x or "" for x in texts.slice(a, b - a).to_pylist()])
                live = np.flatnonzero(table_[what])
                pair = np.unique(who[live].astype(np.int64) << 32 | what[live])  # a feature counts once per text
                total = np.bincount(pair >> 32, table_[pair & 0xFFFFFFFF], b - a) + float(table_[size])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(1 / (1 + np.exp(-np.clip(total, -35, 35))))], names=["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(work, T.StructType([docs.schema["doc_id"], T.StructField("score", T.DoubleType(), False)]))


def op2_toxicity(spark, sf_dir: str) -> DataFrame:
    """Score of every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))
