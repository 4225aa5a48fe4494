"""Text quality by supervised subword embeddings.

A text is the average of learned vectors of its hashed words, of its hashed word pairs, and of hashed byte trigrams (case and symbols kept); a softmax layer tells the classes. Vectors and layer are trained together by numpy
stochastic gradient descent with per-coordinate step sizes. As the layer is linear in the average,
prediction looks up each feature's two class logits, so it costs one table read a feature.

The model is fitted on a bounded sample of labelled rows (``train_rows``, even over the classes, by a hash of
the id, never from the held-out fold); the class shares of all learnable labels set the final offset.
Prediction reads every whole text and nothing else.

Odd input: null or empty text has no feature and gets the offset's score; null labels and labels of
other values than 0 and 1 are not learned from; several labels of one id count as their mean, rounded;
with no labelled row every score is 0.5; a null id is not learned from and held_out is false. Other columns pass through.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_batches, lean, mix, shrink_driver, slices, word_hashes
from .language_id import even_sample, held_out, learnable, trigram_slots

WORDS, GRAMS, PAIRS = 1 << 16, 1 << 16, 1 << 17
#: First slots of the grams and of the pairs; the first slot of each kind stands for nothing.
AT_GRAMS, AT_PAIRS, SLOTS = WORDS, WORDS + GRAMS, WORDS + GRAMS + PAIRS


def features(texts: list[bytes], most: int = 1 << 19):
    """Of consecutive texts: (first, last, word slots, slots of the pairs that words begin, their text starts, gram slots, their text starts)."""
    for lo, hi in slices([len(t) for t in texts], most):
        words = [t.split() for t in texts[lo:hi]]
        tight = [b" ".join(w) for w in words]
        hashes = word_hashes(b" ".join(t for t in tight if t))
        slots = (hashes >> np.uint64(20)).astype(np.int64) % (WORDS - 1) + 1
        starts = np.cumsum([0] + [len(w) for w in words])
        pairs = np.zeros(len(hashes), np.int64)
        if len(hashes) > 1:
            pairs[:-1] = (mix(hashes[:-1] * np.uint64(3) + hashes[1:]) >> np.uint64(20)).astype(np.int64) % (PAIRS - 1) + 1
        lasts = starts[1:][np.diff(starts) > 0] - 1
        pairs[lasts] = 0
        begins = np.cumsum([0] + [len(t) + 2 for t in tight])[:-1]
        grams = trigram_slots(b"  ".join(tight) + b"    ", GRAMS)
        yield lo, hi, slots, pairs, starts, grams, np.append(begins, len(grams))


class SubwordModel:
    """``table``: class logits of each word slot, then of each gram slot, then of each pair slot; ``offset``: class offsets."""

    def __init__(self, table: np.ndarray, offset: np.ndarray):
        self.table, self.offset = table, offset

    @classmethod
    def fit(cls, texts: list[bytes], labels: np.ndarray, prior: float, dim: int = 16, epochs: int = 6, rate: float = 0.5, seed: int = 3) -> SubwordModel:
        rows = []
        for lo, hi, words, pairs, starts, grams, begins in features(texts):
            for i in range(hi - lo):
                mine = slice(starts[i], starts[i + 1])
                ids = np.concatenate((words[mine], AT_GRAMS + grams[begins[i] : begins[i + 1]], AT_PAIRS + pairs[mine]))
                slot, count = np.unique(ids[(ids != AT_GRAMS) & (ids != AT_PAIRS)], return_counts=True)
                rows.append((slot, (count / max(1, count.sum())).astype(np.float32)))
        rng = np.random.default_rng(seed)
        vectors = rng.normal(0, 1 / dim, (SLOTS, dim)).astype(np.float32)
        layer, offset = rng.normal(0, 0.1, (dim, 2)).astype(np.float32), np.zeros(2, np.float32)
        seen_v, seen_l = np.full(SLOTS, 1e-6, np.float32), np.full((dim, 2), 1e-6, np.float32)
        for epoch in range(epochs):
            for i in rng.permutation(len(rows)):
                slot, share = rows[i]
                v = share @ vectors[slot]
                z = v @ layer + offset
                p = np.exp(z - z.max())
                p /= p.sum()
                p[labels[i]] -= 1
                back = layer @ p
                seen_v[slot] += share**2 * float(back @ back)
                vectors[slot] -= (rate * share / np.sqrt(seen_v[slot]))[:, None] * (back / (np.sqrt(dim)))
                g = np.outer(v, p)
                seen_l += g * g
                layer -= rate * 0.2 * g / np.sqrt(seen_l)
                offset -= 0.05 / (1 + epoch) * p
        table = vectors @ layer
        table[[0, AT_GRAMS, AT_PAIRS]] = 0
        if 0 < prior < 1 and len(labels):
            offset = offset + np.log([1 - prior, prior]) - np.log([(labels == 0).mean() or 1.0, (labels == 1).mean() or 1.0])
        return cls(table.astype(np.float32), offset.astype(np.float64))

    def score(self, texts: list[bytes]) -> np.ndarray:
        """Share of class 1."""
        out = np.zeros((len(texts), 2))
        for lo, hi, words, pairs, starts, grams, begins in features(texts):
            sums, counts = np.zeros((hi - lo, 2)), np.diff(starts).astype(np.int64)
            full = np.flatnonzero(counts)
            if len(full):
                sums[full] += np.add.reduceat(self.table[words] + self.table[AT_PAIRS + pairs], starts[:-1][full], axis=0, dtype=np.float64)
            sums += np.add.reduceat(self.table[AT_GRAMS + grams], begins[:-1], axis=0, dtype=np.float64)
            counts = counts + np.maximum(counts - 1, 0) + np.add.reduceat(grams > 0, begins[:-1], dtype=np.int64)
            out[lo:hi] = sums / np.maximum(counts, 1)[:, None]
        z = out + self.offset
        return 1 / (1 + np.exp(np.clip(z[:, 0] - z[:, 1], -60, 60)))


def fit_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", train_rows: int = 3000) -> SubwordModel:
    marks = labels.filter(learnable(id_col) & F.col(label_col).isin(0, 1)).groupBy(F.col(id_col).alias("doc_id")).agg(F.round(F.avg(label_col)).cast("int").alias("label"))
    share = marks.agg(F.avg("label")).first()[0]
    if share is None:
        return SubwordModel(np.zeros((SLOTS, 2), np.float32), np.zeros(2))
    chosen = even_sample(marks, "label", train_rows)
    texts = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    sample = texts.join(F.broadcast(chosen), "doc_id").select("text", "label", "doc_id").toArrow().sort_by([("doc_id", "ascending"), ("text", "ascending")])
    return SubwordModel.fit([t.encode() if t else b"" for t in sample.column(0).to_pylist()], sample.column(1).to_numpy().astype(np.int64), float(share))


def judge_quality(docs: DataFrame, model: SubwordModel, text_col: str = "text", least: float = 0.7, prefix: str = "") -> DataFrame:
    """The rows with score and predicted, each name after ``prefix``."""

    @F.arrow_udf("double")
    @lean()
    def judge(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for array in texts:
            yield pa.array(model.score([t or b"" for t in array.cast(pa.binary()).to_pylist()]), pa.float64())

    told = in_batches(docs).withColumn(prefix + "score", judge(F.col(text_col).cast("string")))
    return told.withColumn(prefix + "predicted", F.when(F.col(prefix + "score") >= least, 1).otherwise(0))


def drop_poor(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The documents predicted as class 1."""
    told = judge_quality(docs, fit_quality(docs, labels, **options), prefix="_quality_")
    shrink_driver(docs.sparkSession)
    return told.filter("_quality_predicted = 1").drop("_quality_score", "_quality_predicted")


def op9_quality(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judge_quality(docs.select("doc_id", "text"), model).select("doc_id", held_out().alias("held_out"), "score", "predicted")
