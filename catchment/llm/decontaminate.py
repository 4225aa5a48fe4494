"""Benchmark decontamination by latent semantic retrieval.

1. Inverse document frequencies of the benchmark's vocabulary are counted over every document.
2. TF-IDF rows of the benchmark passages (long ones in segments) get a randomised SVD for each block of segments: Gaussian
   test vectors, a few power rounds of distributed partial products (each task multiplies its rows both ways, one task
   adds the small matrices up), and a thin decomposition of the last one on the driver. A block's basis has as many directions as
   leave every segment all but a small part of its norm; its size is the block's vocabulary x rank. Blocks are made one after the
   other and lie as files in the shared folder; a task holds a few of them at a time (``HELD`` bytes), whatever the benchmark's size.
3. Every document is read as overlapping word windows. Where the benchmark's vocabulary makes up enough of a
   window's norm for the cosine threshold, its latent vector is a difference of running sums over its words; its
   cosine with each passage gives the candidates. The gate takes each occurrence of a word for itself in the window's norm, which is
   never more than the norm of its counts, so it lets through all that the cosine would; the cosine reported has the true norm
   (words outside the block's vocabulary weigh the vocabulary's mean). The threshold is lowered by the norm
   that a segment has lost in the basis, which makes up for directions left out where a window does not repeat words. A cosine falls when
   a passage's words are frequent in the corpus beside words that are not; so a window is also a candidate where its
   part along a segment reaches half of ``loose`` times the segment's own length, whatever else it holds. Two
   neighbouring windows hold all words of a segment's copy between them, so an exact copy reaches a half in one.
4. A candidate's region goes through longest-common-subsequence: the share of the passage's words found in
   order, in a stretch not much longer than the passage. ``strict`` alone decides; between ``loose`` and
   ``strict`` (a paraphrase) the answer, the passage's last words, must stand there too.

Long passages are covered by segments of at most one window, so dilution is bounded. Words are runs of
letters and digits, lower-cased. Benchmarks of more than ``block`` segments are searched block by block, each with a
vocabulary and a basis of its own.

Odd input: null or word-less text matches nothing; null or word-less passages are ignored; repeated passages
each report; a null document id is reported as null; an empty table on either side gives no matches. Other columns pass through
``drop_contaminated`` untouched.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U, by_bytes, file_system, fresh_path, hashed_texts, in_batches, lean, materialize, shrink_driver, slices, word_hashes, worker_store

#: The least share of its squared norm that a segment keeps in its block's basis.
KEPT = 0.998
_WORDS = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or 48 <= b <= 57 or b >= 128 else 32 for b in range(256))


def split_words(text: bytes) -> list[bytes]:
    return text.translate(_WORDS).split()


def common_subsequence(item: list, region: list) -> int:
    """Length of the longest common subsequence, bit-parallel over the passage."""
    masks: dict = {}
    for i, w in enumerate(item):
        masks[w] = masks.get(w, 0) | 1 << i
    full = (1 << len(item)) - 1
    v = full
    for w in region:
        m = masks.get(w)
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & full
    return len(item) - v.bit_count()


def best_region(item: list, words: list, slack: float = 1.5) -> tuple[int, int]:
    """The largest common subsequence within any stretch of slack x the passage's length; and where that stretch begins."""
    span = max(len(item) + 4, int(len(item) * slack))
    vocabulary = set(item)
    hits = [i for i, w in enumerate(words) if w in vocabulary]
    best, at = 0, 0
    step = max(1, len(item) // 8)
    last = -step
    for h in hits:
        if h - last < step:
            continue
        last = h
        n = common_subsequence(item, words[max(0, h - step) : h - step + span + step])
        if n > best:
            best, at = n, h
    return best, at


class LatentIndex:
    """A block of segments in latent space: vocabulary hashes, idf, basis rows, segment vectors, the norm each has lost,
    the number of each one's passage (``owner``), and the passages themselves as number -> (item, words); the lengths of the rows before
    these are made units, and the most that one occurrence of each word adds to a window's part along any of them."""

    def __init__(self, passages, vocabulary, idf, mean, basis, segments, owner, lengths, most):
        self.passages, self.vocabulary, self.idf, self.mean, self.basis, self.segments, self.owner = passages, vocabulary, idf, mean, basis, segments, owner
        self.lengths, self.most = lengths, most
        self.rank = basis.shape[1]
        self.lost = np.sqrt(np.maximum(0, 1 - (segments.astype(np.float64) ** 2).sum(axis=1)))


#: Bytes of index blocks that a worker holds.
HELD = 1 << 26


class IndexFiles:
    """The blocks of a benchmark's index as files in the shared folder."""

    def __init__(self, root: str):
        self.root, self.names = root, []

    def add(self, index: LatentIndex) -> None:
        fs, base = file_system(self.root)
        fs.create_dir(base, recursive=True)
        name = f"block-{len(self.names):06d}.index"
        with fs.open_output_stream(f"{base}/{name}", compression=None) as f:
            f.write(pickle.dumps(index, protocol=5))
        self.names.append(name)

    def __iter__(self) -> Iterator[LatentIndex]:
        held = worker_store("latent")
        if held.get("root") != self.root:
            held.clear()
            held.update(root=self.root, blocks={}, bytes=0)
        for name in self.names:
            index = held["blocks"].get(name)
            if index is None:
                fs, base = file_system(self.root)
                with fs.open_input_file(f"{base}/{name}") as f:
                    data = f.read()
                index = pickle.loads(data)
                if held["bytes"] + len(data) <= HELD:
                    held["blocks"][name] = index
                    held["bytes"] += len(data)
            yield index

    def __bool__(self) -> bool:
        return bool(self.names)


def _hash_words(words: list[bytes]) -> np.ndarray:
    return word_hashes(b" ".join(words))


def in_vocabulary(hashes: np.ndarray, vocabulary: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which hashes are in the sorted vocabulary, and their places there; a table of leading bits clears most others."""
    if not len(hashes) or not len(vocabulary):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    table = np.zeros(1 << 20, bool)
    table[(vocabulary >> U(44)).astype(np.int64)] = True
    places = np.flatnonzero(table[(hashes >> U(44)).astype(np.int64)])
    some = hashes[places]
    at = np.minimum(np.searchsorted(vocabulary, some), len(vocabulary) - 1)
    ok = vocabulary[at] == some
    return places[ok], at[ok]


def document_frequency(docs: DataFrame, vocabulary: np.ndarray, text_col: str = "text") -> tuple[np.ndarray, int]:
    """How many documents hold each word of the sorted vocabulary, and how many documents there are, over all rows."""

    @lean()
    def count(batches):
        total, seen = 0, np.zeros(len(vocabulary), np.int64)
        for batch in by_bytes(batches, 0):
            texts = batch.column(0).cast(pa.binary()).to_pylist()
            total += len(texts)
            for lo, hi in slices([len(t or b"") for t in texts], 1 << 19):
                h, begins = hashed_texts([(t or b"").translate(_WORDS) for t in texts[lo:hi]])
                places, known = in_vocabulary(h, vocabulary)
                doc = np.searchsorted(begins, places, side="right")
                pairs = np.unique(doc * len(vocabulary) + known)
                seen += np.bincount(pairs % len(vocabulary), minlength=len(vocabulary))
        yield pa.RecordBatch.from_arrays([pa.array([total]), pa.array([seen.tobytes()], pa.binary())], names=["total", "seen"])

    partial = in_batches(docs).select(F.col(text_col).cast("string").alias("text")).mapInArrow(count, "total long, seen binary")

    def add(batches):
        total, seen = 0, np.zeros(len(vocabulary), np.int64)
        for batch in batches:
            total += sum(batch.column(0).to_pylist())
            for s in batch.column(1).to_pylist():
                seen += np.frombuffer(s, np.int64)
        yield pa.RecordBatch.from_arrays([pa.array([total]), pa.array([seen.tobytes()], pa.binary())], names=["total", "seen"])

    rows = partial.repartition(8).mapInArrow(add, "total long, seen binary").collect()
    return sum((np.frombuffer(r["seen"], np.int64) for r in rows), np.zeros(len(vocabulary), np.int64)), sum(r["total"] for r in rows)


def randomised_basis(rows: DataFrame, vocabulary: np.ndarray, idf: np.ndarray, rank: int, rounds: int = 2, seed: int = 5) -> np.ndarray:
    """Leading right singular directions (vocabulary x rank) of the TF-IDF rows of ``rows`` (column words: array<binary>)."""
    start = np.random.default_rng(seed).normal(size=(len(vocabulary), rank)).astype(np.float32)
    basis, _ = np.linalg.qr(start)

    def multiply(basis):
        def run(batches):
            out = np.zeros((len(vocabulary), basis.shape[1]), np.float32)
            for batch in batches:
                for words in batch.column(0).to_pylist():
                    at, weight = weigh(_hash_words(words), vocabulary, idf)
                    if len(at):
                        out[at] += weight[:, None] * (weight @ basis[at])
            yield pa.RecordBatch.from_arrays([pa.array([out.tobytes()], pa.binary())], names=["part"])

        return run

    def add(batches):
        total = None
        for batch in batches:
            for part in batch.column(0).to_pylist():
                one = np.frombuffer(part, np.float32)
                total = one.copy() if total is None else total + one
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["part"])

    for _ in range(rounds + 1):
        parts = rows.select("words").mapInArrow(multiply(basis), "part binary").coalesce(1).mapInArrow(add, "part binary").collect()
        total = sum((np.frombuffer(p["part"], np.float32).reshape(len(vocabulary), -1) for p in parts), np.zeros((len(vocabulary), rank), np.float32))
        basis, values, _ = np.linalg.svd(total.astype(np.float64), full_matrices=False)
        basis = basis[:, values > 1e-9 * max(values[0], 1e-30)].astype(np.float32)
        if not basis.shape[1]:
            break
        rank = basis.shape[1]
    return np.ascontiguousarray(basis)


def weigh(hashes: np.ndarray, vocabulary: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit TF-IDF row of a passage: distinct vocabulary places and weights."""
    if not len(hashes):
        return np.empty(0, np.int64), np.empty(0, np.float32)
    at = np.minimum(np.searchsorted(vocabulary, hashes), len(vocabulary) - 1)
    at, tf = np.unique(at[vocabulary[at] == hashes], return_counts=True)
    w = (tf * idf[at]).astype(np.float32)
    return at, w / max(float(np.linalg.norm(w)), 1e-12)


def benchmark_vocabulary(rows: DataFrame) -> np.ndarray:
    """Sorted hashes of the distinct words of all passages (column words): eight bytes a word."""

    def run(batches):
        for batch in batches:
            hashes = np.unique(_hash_words([w for ws in batch.column(0).to_pylist() for w in ws]))
            yield pa.RecordBatch.from_arrays([pa.array(hashes.view(np.int64))], names=["h"])

    found = rows.select("words").mapInArrow(run, "h long").distinct().toArrow().column(0).to_numpy()
    return np.unique(found.view(np.uint64))


def build_indexes(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", rank: int = 128, window: int = 48, block: int = 256) -> IndexFiles:
    """Latent indexes of all passages, one a block of ``block`` segments: ``rank`` directions, and more until each segment keeps ``KEPT``."""
    passages = in_batches(benchmark).filter(F.col(item_text_col).isNotNull()).select(F.col(item_col).cast("long").alias("item"), F.col(item_text_col).cast("string").alias("text"))

    @F.arrow_udf("array<binary>")
    @lean()
    def cut(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for array in texts:
            yield pa.array([split_words(t) for t in array.cast(pa.binary()).to_pylist()], pa.list_(pa.binary()))

    out = IndexFiles(fresh_path(docs.sparkSession, "latent"))
    rows = materialize(passages.withColumn("words", cut("text")).select("item", "words"), "passages").filter("size(words) > 0")
    vocabulary = benchmark_vocabulary(rows)
    if not len(vocabulary):
        return out
    seen, total = document_frequency(docs, vocabulary, text_col)
    idf = np.log((total + 1) / (seen + 1)) + 0.1
    mean = float(idf.astype(np.float32).mean())
    starts = lambda n: range(0, n - window // 2, window) if n > window else (0,)
    held: list[tuple[int, list]] = []
    known: dict[int, tuple] = {}

    def close(some: list[tuple[int, list]]) -> None:
        owner, parts = zip(*some)
        own = np.unique(_hash_words([w for ws in parts for w in ws]))
        weights = idf[np.searchsorted(vocabulary, own)]
        frame = docs.sparkSession.createDataFrame(pa.table({"words": pa.array(parts, pa.list_(pa.binary()))}))
        basis = randomised_basis(frame, own, weights, min(len(parts), len(own)))
        v = np.array([w @ basis[at] for at, w in (weigh(_hash_words(ws), own, weights) for ws in parts)], np.float32)
        kept = np.cumsum(v.astype(np.float64) ** 2, axis=1).min(axis=0)
        n = min(max(rank, int(np.searchsorted(kept, KEPT)) + 1), basis.shape[1])
        lengths, most = np.zeros(len(parts)), np.zeros(len(own))
        for k, ws in enumerate(parts):
            at, tf = np.unique(np.searchsorted(own, _hash_words(ws)), return_counts=True)
            lengths[k] = np.linalg.norm(tf * weights[at])
            most[at] = np.maximum(most[at], tf * (weights[at] / lengths[k]) ** 2)
        out.add(LatentIndex({k: known[k] for k in set(owner)}, own, weights.astype(np.float32), mean, np.ascontiguousarray(basis[:, :n]), np.ascontiguousarray(v[:, :n]), np.array(owner), lengths, most))

    for k, row in enumerate(rows.orderBy("item").toLocalIterator()):
        known = {i: known[i] for i, _ in held} | {k: (row["item"], [bytes(w) for w in row["words"]])}
        held += [(k, known[k][1][s : s + window]) for s in starts(len(known[k][1]))]
        while len(held) >= block:
            close(held[:block])
            held = held[block:]
    if held:
        close(held)
    return out


def near(index: LatentIndex, h: np.ndarray, begins: np.ndarray, owner: np.ndarray, firsts: np.ndarray, ends: np.ndarray, cosine: float, part: float):
    """For each text with candidates: its place, and (window, segment, cosine) of the pairs at or above either threshold."""
    places, known = in_vocabulary(h, index.vocabulary)
    # what share of each window's norm lies in the vocabulary
    wide = np.searchsorted(places, np.stack((firsts, ends)))
    weight = index.idf[known]
    inside = np.concatenate(([0.0], np.cumsum(weight.astype(np.float64) ** 2)))
    own = inside[wide[1]] - inside[wide[0]]
    norm = np.sqrt(own + ((ends - firsts) - (wide[1] - wide[0])) * index.mean**2) + 1e-9
    along = np.concatenate(([0.0], np.cumsum(index.most[known])))
    rich = np.flatnonzero((np.sqrt(own) >= cosine * norm) | (along[wide[1]] - along[wide[0]] >= part - 1e-6))
    cuts = np.searchsorted(owner[rich], np.arange(len(begins)))
    least = cosine - index.lost
    for i in np.flatnonzero(np.diff(cuts)).tolist():
        mine = rich[cuts[i] : cuts[i + 1]]
        a, b = wide[0][mine[0]], wide[1][mine[-1]]
        vectors = np.concatenate((np.zeros((1, index.rank), np.float32), np.cumsum(weight[a:b, None] * index.basis[known[a:b]], axis=0)))
        dot = (vectors[wide[1][mine] - a] - vectors[wide[0][mine] - a]) @ index.segments.T
        cos = dot / norm[mine][:, None]
        near_w, near_s = np.nonzero((cos >= least) | (dot >= part * index.lengths - np.sqrt(own[mine])[:, None] * index.lost - 1e-4))
        if len(near_w):
            hit = np.unique(near_w)
            true = np.ones(len(mine))
            true[hit] = [_norm(h[firsts[w] : ends[w]], known[wide[0][w] : wide[1][w]], places[wide[0][w] : wide[1][w]] - firsts[w], index) for w in mine[hit].tolist()]
            yield i, mine[near_w], near_s, dot[near_w, near_s] / true[near_w]


def _norm(hashes: np.ndarray, known: np.ndarray, places: np.ndarray, index: LatentIndex) -> float:
    """The norm of a window's TF-IDF row: counts of its distinct words, those outside the vocabulary at its mean weight."""
    at, tf = np.unique(known, return_counts=True)
    other = np.delete(hashes, places)
    _, more = np.unique(other, return_counts=True)
    return float(np.sqrt(((tf * index.idf[at].astype(np.float64)) ** 2).sum() + (more.astype(np.float64) ** 2).sum() * index.mean**2)) or 1.0


def search(indexes, texts: list, window: int, cosine: float, loose: float, strict: float, answer: int):
    """For each text its matches: (item, cosine, common share, answer found, first word)."""
    stride = window // 2
    for lo, hi in slices([len(t or b"") for t in texts], 1 << 20):
        clean = [(t or b"").translate(_WORDS) for t in texts[lo:hi]]
        h, begins = hashed_texts(clean)
        # all windows of all texts: first word and end
        sizes = np.diff(begins)
        counts = np.where(sizes > 0, np.maximum(1, -(-(sizes - stride) // stride)), 0)
        owner = np.repeat(np.arange(len(clean)), counts)
        turn = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
        firsts = begins[:-1][owner] + turn * stride
        ends = np.minimum(firsts + window, begins[1:][owner])
        pairs: dict[int, list] = {}
        passages: dict[int, tuple] = {}
        for index in indexes:
            for i, windows, near_s, cos in near(index, h, begins, owner, firsts, ends, cosine, loose / 2):
                pairs.setdefault(i, []).append((index.owner[near_s], firsts[windows] - begins[i], cos))
                passages.update({k: index.passages[k] for k in set(index.owner[near_s].tolist())})
        for i, text in enumerate(clean):
            if i not in pairs:
                yield []
                continue
            words = text.split()
            near_k, near_first, near_cos = (np.concatenate(x) for x in zip(*pairs[i]))
            best: dict = {}
            for k in np.unique(near_k).tolist():
                of = near_k == k
                name, item = passages[k]
                marks = sorted({int(f) for f in near_first[of]})
                top = float(near_cos[of].max())
                regions: list[list[int]] = []
                for f in marks:
                    a0, b0 = max(0, f - len(item)), min(len(words), f + window + len(item))
                    if regions and a0 <= regions[-1][1]:
                        regions[-1][1] = b0
                    else:
                        regions.append([a0, b0])
                for a0, b0 in regions:
                    # no subsequence is longer than the number of passage words that occur here at all
                    if sum(map(set(words[a0:b0]).__contains__, item)) < loose * len(item):
                        continue
                    n, off = best_region(item, words[a0:b0])
                    share = n / len(item)
                    tail = item[-answer:]
                    told = common_subsequence(tail, words[a0:b0]) >= max(1, len(tail) - 1)
                    if (share >= strict or (share >= loose and told)) and (k not in best or best[k][2] < share):
                        best[k] = (name, top, share, told, a0 + off)
            yield [best[k] for k in sorted(best)]


def _matches(indexes, texts, window, cosine, loose, strict, answer):
    return list(search(indexes, texts, window, cosine, loose, strict, answer)) if indexes else [[] for _ in texts]


MATCH = "array<struct<item_id:bigint,cosine:double,common_share:double,answer_found:boolean,first_word:bigint>>"


def with_matches(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", column: str = "matches", window: int = 48, cosine: float = 0.25, loose: float = 0.6, strict: float = 0.75, answer: int = 4, rank: int = 128) -> DataFrame:
    """The rows with an array of their matches with benchmark passages (empty for clean documents).

    A column of ``docs`` that has the result's name is replaced.
    """
    files = build_indexes(docs, benchmark, text_col, rank=rank, window=window)
    kind = pa.list_(pa.struct([("item_id", pa.int64()), ("cosine", pa.float64()), ("common_share", pa.float64()), ("answer_found", pa.bool_()), ("first_word", pa.int64())]))
    names = ("item_id", "cosine", "common_share", "answer_found", "first_word")

    @F.arrow_udf(MATCH)
    @lean("latent")
    def find(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for array in texts:
            found = _matches(files, array.cast(pa.binary()).to_pylist(), window, cosine, loose, strict, answer)
            yield pa.array([[dict(zip(names, m)) for m in some] for some in found], kind)

    return in_batches(docs).withColumn(column, find(F.col(text_col).cast("string")))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents that match no benchmark passage."""
    mark = "_benchmark_matches"
    found = with_matches(docs, benchmark, column=mark, **options)
    shrink_driver(docs.sparkSession)
    return found.filter(F.size(mark) == 0).drop(mark)


def op1_benchmark_decontamination(spark, sf_dir: str) -> DataFrame:
    """One row for each document and passage it holds."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = with_matches(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.select("doc_id", F.explode("matches").alias("m")).select("doc_id", "m.item_id", "m.cosine", "m.common_share", "m.answer_found", "m.first_word")
