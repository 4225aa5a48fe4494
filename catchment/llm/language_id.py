"""Language identification by error-correcting output codes over hashed character n-grams.

Every learned language has a codeword; each bit has a binary classifier (weights over hashed byte
trigrams of the lower-cased letters of a text, averaged over the whole text, with a logistic scale and
offset). A text's bit margins are decoded by weighted logistic loss against every codeword, a bit
weighing as much as its classifier did better than chance in training. The nearest codeword wins;
its softmax share is the score, and a text whose two nearest codewords lie within ``ambiguity`` of
each other in loss is flagged ambiguous.

The model is fitted on a bounded sample of labelled rows (``train_rows`` in all, or one a language where there are
more languages; spread evenly over the languages, chosen by a hash of the id); prediction reads every whole text and nothing but the text.

Odd input: null text, or text without any letter, is ``und`` with score 0, not ambiguous; with no
labelled row every text is ``und``; with one language every text with a letter is that language. Ties
go to the codeword first in alphabetical order. Other columns pass through untouched; where one has a name of the
result, the result replaces it. A null id is in no fold: it is never learned from, and held_out is false.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import in_batches, lean, shrink_driver, slices

BUCKETS = 1 << 16
_LETTER = re.compile(r"[^\W\d_]")
_KEEP = bytes(b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
RESULT = "struct<lang_pred:string,score:double,ambiguous:boolean>"


def held_out(id_col: str = "doc_id"):
    """Whether a row is in the fold that is never learned from."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def learnable(id_col: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 != 2, F.lit(False))


def trigram_slots(joined: bytes, buckets: int) -> np.ndarray:
    """A bucket from 1 on for each byte trigram, 0 for those that hold a part of a double space (between texts), so
    that no text's trigrams depend on its neighbours."""
    b = np.frombuffer(joined, np.uint8).astype(np.uint32)
    code = (b[:-2] << np.uint32(16)) | (b[1:-1] << np.uint32(8)) | b[2:]
    slot = ((code * np.uint32(2654435761)) >> np.uint32(8)) % np.uint32(buckets - 1) + np.uint32(1)
    gap = (b[:-1] == 32) & (b[1:] == 32)
    slot[gap[:-1] | gap[1:] | np.concatenate(([False], gap))[: len(slot)]] = 0
    return slot.astype(np.int64)


def slot_runs(texts: list[bytes], buckets: int, most: int = 1 << 19):
    """Of consecutive texts: (first, last, slots, where each text's slots begin)."""
    for lo, hi in slices([len(t) for t in texts], most):
        part = texts[lo:hi]
        begins = np.cumsum([0] + [len(t) + 2 for t in part])[:-1]
        yield lo, hi, trigram_slots(b"  ".join(part) + b"    ", buckets), begins


def letters(text: str) -> bytes:
    return b" ".join(text.lower().encode().translate(_KEEP).split())


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """n codewords of +1/-1: all distinct splits for up to five languages, else the best spread of random codes."""
    if n <= 5:
        bits = [[1 if i == 0 or not m >> (i - 1) & 1 else -1 for i in range(n)] for m in range(1, 1 << max(0, n - 1))]
        return np.array(bits, np.float64).reshape(-1, n).T if bits else np.ones((n, 0))
    rng, width, best, spread = np.random.default_rng(seed), 12 * int(np.ceil(np.log2(n))), None, -1
    for _ in range(50):
        code = rng.choice([-1.0, 1.0], (n, width))
        code = code[:, np.abs(code.sum(axis=0)) < n]
        apart = code.shape[1] - (code @ code.T + code.shape[1]) / 2
        least = (apart + np.eye(n) * 1e9).min()
        if least > spread:
            best, spread = code, least
    return best


class OutputCodes:
    """The fitted model: ``langs``, ``code``, ``weights`` (bucket x bit), per-bit ``scale``, ``offset``, ``trust``."""

    def __init__(self, langs, code, weights, scale, offset, trust, ambiguity):
        self.langs, self.code, self.weights, self.scale, self.offset, self.trust, self.ambiguity = langs, code, weights, scale, offset, trust, ambiguity

    @staticmethod
    def margins(texts: list[bytes], weights: np.ndarray) -> np.ndarray:
        out = np.zeros((len(texts), weights.shape[1]), np.float64)
        for lo, hi, slots, begins in slot_runs(texts, len(weights)):
            sums = np.add.reduceat(weights[slots], begins, axis=0, dtype=np.float64)
            counts = np.add.reduceat(slots > 0, begins, dtype=np.int64)
            out[lo:hi] = sums / np.maximum(counts, 1)[:, None]
        return out

    @classmethod
    def fit(cls, texts: list[str], labels: list[str], ambiguity: float = 0.5, smooth: float = 0.5) -> OutputCodes:
        langs = sorted(set(labels))
        y = np.array([langs.index(x) for x in labels], np.int64)
        code = codewords(len(langs))
        clean = [letters(t) for t in texts]
        counts = np.zeros((len(langs), BUCKETS))
        for lo, hi, slots, begins in slot_runs(clean, BUCKETS):
            ends = np.append(begins[1:], len(slots))
            for i, a, b in zip(range(lo, hi), begins, ends):
                counts[y[i]] += np.bincount(slots[a:b], minlength=BUCKETS)
        counts[:, 0] = 0
        share = (counts + smooth) / (counts.sum(axis=1, keepdims=True) + smooth * BUCKETS)
        weights = np.zeros((BUCKETS, code.shape[1]), np.float32)
        for j in range(code.shape[1]):
            weights[:, j] = np.log(share[code[:, j] > 0].mean(axis=0)) - np.log(share[code[:, j] < 0].mean(axis=0))
        weights[0] = 0
        m = cls.margins(clean, weights)
        scale, offset, trust = (np.zeros(code.shape[1]) for _ in range(3))
        for j in range(code.shape[1]):
            scale[j], offset[j] = logistic(m[:, j], code[y, j])
            right = (np.sign(m[:, j] * scale[j] + offset[j]) == code[y, j]).mean()
            trust[j] = max(0.05, 2 * right - 1)
        return cls(langs, code, weights, scale, offset, trust, ambiguity)

    def predict(self, texts: list) -> tuple[list, np.ndarray, np.ndarray]:
        n = len(texts)
        known = np.array([t is not None and _LETTER.search(t) is not None for t in texts], bool) & bool(self.langs)
        pred, score, close = np.full(n, -1), np.zeros(n), np.zeros(n, bool)
        at = np.flatnonzero(known)
        if len(at):
            z = self.margins([letters(texts[i]) for i in at], self.weights) * self.scale + self.offset
            loss = np.stack([(np.logaddexp(0, -z * c) * self.trust).sum(axis=1) for c in self.code], axis=1)
            pred[at] = loss.argmin(axis=1)
            share = np.exp(-(loss - loss.min(axis=1, keepdims=True)))
            score[at] = 1 / share.sum(axis=1)
            if len(self.langs) > 1:
                two = np.partition(loss, 1, axis=1)
                close[at] = two[:, 1] - two[:, 0] < self.ambiguity
        return [self.langs[i] if i >= 0 else "und" for i in pred], score, close


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 40) -> tuple[float, float]:
    """Scale and offset of a one-feature logistic model, y in {-1, 1}, by damped Newton steps."""
    spread = float(np.abs(x).mean()) or 1.0
    a = np.stack([x / spread, np.ones_like(x)], axis=1)
    w = np.zeros(2)
    t = (y > 0) * 1.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        g = a.T @ (p - t) + ridge * w
        h = (a * (p * (1 - p))[:, None]).T @ a + ridge * np.eye(2)
        step = np.linalg.solve(h, g)
        w -= np.clip(step, -5, 5)
    return float(w[0] / spread), float(w[1])


def even_sample(rows: DataFrame, label: str, want: int, id_col: str = "doc_id") -> DataFrame:
    """(id, label): about ``want`` rows in all, as many of every label (one at least), those with the least hash of the id.

    Each task keeps only its own least ones of a label, so a label with most of the rows is no load for one task.
    """
    pairs = rows.select(id_col, label)
    each = max(1, want // max(1, pairs.agg(F.count_distinct(label)).first()[0]))
    grade = F.xxhash64(id_col, F.lit(23))
    w = Window.partitionBy(label).orderBy(grade, id_col)
    return pairs.withColumn("_k", F.row_number().over(w)).filter(F.col("_k") <= each).drop("_k")


def fit_languages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", train_rows: int = 2000, ambiguity: float = 0.5) -> OutputCodes:
    rows = docs.filter(learnable(id_col) & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("doc_id"), F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"))
    chosen = even_sample(rows, "lang", train_rows).distinct()
    sample = rows.join(F.broadcast(chosen), ["doc_id", "lang"]).toArrow().sort_by([("doc_id", "ascending"), ("text", "ascending")])
    return OutputCodes.fit(sample.column("text").to_pylist(), sample.column("lang").to_pylist(), ambiguity)


def identify(docs: DataFrame, model: OutputCodes, text_col: str = "text", prefix: str = "") -> DataFrame:
    """The rows with lang_pred, score and ambiguous, each name after ``prefix``."""

    @F.arrow_udf(RESULT)
    @lean()
    def judge(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for array in texts:
            pred, score, close = model.predict(array.to_pylist())
            yield pa.StructArray.from_arrays([pa.array(pred, pa.string()), pa.array(score), pa.array(close)], ["lang_pred", "score", "ambiguous"])

    told = in_batches(docs).withColumn("_told", judge(F.col(text_col).cast("string")))
    return told.withColumns({prefix + c: F.col(f"_told.{c}") for c in ("lang_pred", "score", "ambiguous")}).drop("_told")


def drop_unidentified(docs: DataFrame, least: float = 0.5, **options) -> DataFrame:
    """The documents with a language: those without a letter go, and those that stay ambiguous at a score below ``least``."""
    told = identify(docs, fit_languages(docs, **options), prefix="_lid_")
    shrink_driver(docs.sparkSession)
    kept = told.filter("_lid_lang_pred != 'und' and not (_lid_ambiguous and _lid_score < %r)" % least)
    return kept.drop("_lid_lang_pred", "_lid_score", "_lid_ambiguous")


def op8_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    told = identify(docs.select("doc_id", "text"), fit_languages(docs))
    return told.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "ambiguous")
