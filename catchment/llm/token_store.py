"""Token-id shards and a minimal perfect hash index over their documents.

Shard file: 16 bytes ``TOKSHARD`` + version and id width (two little-endian uint32), then the ids of
its documents in ascending key order, raw, 2 bytes each where the vocabulary allows, else 4. Shards
hold consecutive key ranges; each document ends with the end id.

Index part file: 24 bytes ``TOKINDEX`` + key count and level count (uint64), the level sizes in words
(uint64 each), the level bitmaps, their running ranks (uint64 a word), then by slot: fingerprints
(uint32), shards (uint32), offsets in ids (uint64), id counts (uint64). A key falls into a part by one
hash, finds its slot by the first level bitmap that holds it (a key that collides at one level goes
down to the next), and is there only if the stored fingerprint agrees: a handful of reads whatever
the number of keys. ``part_keys`` bounds what one task holds while it builds a part.

Keys are (document id, occurrence): rows that repeat an id get the occurrences 0, 1, ... in text
order; a null id is a key of its own, before all others. Null text is the end id alone. An empty table
writes no shard. Columns other than id and text are ignored. A lost executor leaves at worst a stray file:
names hold the attempt, and readers follow only what the finished tasks report.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U, by_bytes, file_system, fresh_path, in_batches, lean, materialize, mix
from .packing import vocabulary_path
from .tokens import encoded, encoder

_SHARD, _INDEX = b"TOKSHARD", b"TOKINDEX"


class PerfectHash:
    """A minimal perfect hash over distinct (h, g) pairs of 64-bit hashes, in level bitmaps."""

    def __init__(self, levels: list[np.ndarray]):
        self.levels = levels
        counts = [np.bitwise_count(b).astype(np.uint64) for b in levels]
        flat = np.concatenate(counts) if counts else np.empty(0, np.uint64)
        ranks = np.concatenate(([0], np.cumsum(flat)[:-1])).astype(np.uint64) if len(flat) else flat
        self.ranks = np.split(ranks, np.cumsum([len(b) for b in levels])[:-1]) if levels else []

    @staticmethod
    def _place(h, g, level, words):
        return mix(h + g * U(2 * level + 1) + U(level)) % U(64 * words)

    @classmethod
    def build(cls, h: np.ndarray, g: np.ndarray, load: float = 0.5) -> PerfectHash:
        levels = []
        while len(h):
            if len(levels) == 64:
                raise ValueError("two keys have equal hashes")
            words = max(1, int(len(h) / load) // 64 + 1)
            at = cls._place(h, g, len(levels), words).astype(np.int64)
            seen = np.bincount(at, minlength=64 * words)
            alone = seen == 1
            levels.append(np.packbits(alone, bitorder="little").view("<u8").astype(np.uint64))
            left = ~alone[at]
            h, g = h[left], g[left]
        return cls(levels)

    def slots(self, h: np.ndarray, g: np.ndarray) -> np.ndarray:
        """The slot of each key, -1 where no level holds it (it is no key)."""
        out = np.full(len(h), -1, np.int64)
        left = np.arange(len(h))
        for k, (bits, ranks) in enumerate(zip(self.levels, self.ranks)):
            at = self._place(h[left], g[left], k, len(bits))
            word, bit = (at >> U(6)).astype(np.int64), at & U(63)
            held = (bits[word] >> bit) & U(1) == 1
            below = np.bitwise_count(bits[word[held]] & ((U(1) << bit[held]) - U(1)))
            out[left[held]] = (ranks[word[held]] + below).astype(np.int64)
            left = left[~held]
        return out


def fingerprint(h, g):
    return (mix(g ^ (h << U(1))) >> U(32)).astype(np.uint32)


def index_bytes(h, g, shard, offset, count) -> bytes:
    mph = PerfectHash.build(h, g)
    slot = mph.slots(h, g)

    def by_slot(x, kind):
        a = np.zeros(len(h), kind)
        a[slot] = x
        return a.tobytes()

    head = _INDEX + np.array([len(h), len(mph.levels)], "<u8").tobytes() + np.array([len(b) for b in mph.levels], "<u8").tobytes()
    maps = b"".join(b.astype("<u8").tobytes() for b in mph.levels) + b"".join(r.astype("<u8").tobytes() for r in mph.ranks)
    return head + maps + by_slot(fingerprint(h, g), "<u4") + by_slot(shard, "<u4") + by_slot(offset, "<u8") + by_slot(count, "<u8")


class IndexPart:
    """One part, read from its bytes; arrays are views of them."""

    def __init__(self, data: bytes):
        if data[:8] != _INDEX:
            raise ValueError("not an index part")
        n, levels = np.frombuffer(data, "<u8", 2, 8).tolist()
        sizes = np.frombuffer(data, "<u8", levels, 24).tolist()
        at = 24 + 8 * levels

        def take(kind, count):
            nonlocal at
            a = np.frombuffer(data, kind, count, at)
            at += a.nbytes
            return a

        bits = [take("<u8", s) for s in sizes]
        ranks = [take("<u8", s) for s in sizes]
        self.mph = PerfectHash.__new__(PerfectHash)
        self.mph.levels, self.mph.ranks = bits, ranks
        self.prints, self.shard, self.offset, self.count = take("<u4", n), take("<u4", n), take("<u8", n), take("<u8", n)

    def find(self, h, g):
        """(found, shard, offset, count) of each key."""
        slot = self.mph.slots(h, g)
        ok = slot >= 0
        ok[ok] = self.prints[slot[ok]] == fingerprint(h[ok], g[ok])
        slot = np.where(ok, slot, 0)
        pick = lambda a: a[slot].astype(np.int64) if len(a) else np.zeros(len(slot), np.int64)
        return ok, pick(self.shard), pick(self.offset), pick(self.count)


def _write(root: str, path: str, end_id: int):
    schema = pa.schema([("doc_id", pa.int64()), ("occurrence", pa.int64()), ("shard", pa.int64()), ("file", pa.string()), ("offset", pa.int64()), ("n_tokens", pa.int64())])

    @lean("encoders")
    def run(batches):
        context = TaskContext.get()
        shard, out, at, last, again = context.partitionId(), None, 0, (), 0
        name = f"shard-{shard:06d}-{context.taskAttemptId()}.ids"
        fs, base = file_system(root)
        try:
            for batch in by_bytes(batches, 1):
                if not batch.num_rows:
                    continue
                if out is None:
                    wide = len(encoder(path).ends) > 65536
                    fs.create_dir(base, recursive=True)
                    out = fs.open_output_stream(f"{base}/{name}")
                    out.write(_SHARD + np.array([1, 4 if wide else 2], "<u4").tobytes())
                ids, sizes = encoded(batch.column(1), path, end_id)
                out.write(ids.astype("<u4" if wide else "<u2").tobytes())
                docs, again_of = batch.column(0).to_pylist(), []
                for doc in docs:
                    again = again + 1 if last == (doc,) else 0
                    last = (doc,)
                    again_of.append(again)
                stops = np.cumsum(sizes)
                n = len(docs)
                yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(again_of, pa.int64()), pa.array(np.full(n, shard)), pa.array([name] * n), pa.array(at + stops - sizes), pa.array(sizes)], schema=schema)
                at += int(stops[-1])
        finally:
            if out is not None:
                out.close()

    return run


def _build(root: str):
    def run(table: pa.Table) -> pa.Table:
        part = table.column("part")[0].as_py()
        h, g = (table.column(c).to_numpy().view(np.uint64) for c in ("h", "g"))
        data = index_bytes(h, g, *(table.column(c).to_numpy() for c in ("shard", "offset", "n_tokens")))
        fs, base = file_system(root)
        name = f"part-{part:06d}-{TaskContext.get().taskAttemptId()}.mph"
        fs.create_dir(base, recursive=True)
        with fs.open_output_stream(f"{base}/{name}") as out:
            out.write(data)
        return pa.table({"part": [part], "part_file": [name], "keys": [len(h)], "bytes": [len(data)]})

    return run


def hashed_keys(df: DataFrame, parts: int) -> DataFrame:
    h = F.xxhash64("doc_id", "occurrence")
    return df.withColumn("h", h).withColumn("g", F.xxhash64("occurrence", "doc_id", F.lit(11))).withColumn("part", F.pmod(F.shiftrightunsigned("h", 20), F.lit(parts)))


class TokenStore:
    """Where shards and index lie: ``records`` (one row a document), ``bases`` (ids before each shard)."""

    def __init__(self, spark, root, files, parts):
        self.spark, self.root, self.files, self.parts = spark, root, files, parts

    def read(self, keys: DataFrame) -> DataFrame:
        """Keyed access: (doc_id, occurrence) rows to their (start, n_tokens, ids_crc32), through the index.

        Keys meet their index part, then their shard; keys that the store lacks get no row.
        """
        root, parts = self.root, dict(self.parts)
        found_schema = pa.schema([("doc_id", pa.int64()), ("occurrence", pa.int64()), ("shard", pa.int64()), ("offset", pa.int64()), ("n_tokens", pa.int64())])

        def look(batches):
            fs, base = file_system(root)
            held, index = None, None
            for batch in batches:
                of = batch.column(4).to_numpy()
                for lo, hi in zip(*runs(of)):
                    if of[lo] != held:
                        held = of[lo]
                        name = parts.get(int(held))
                        index = None
                        if name:
                            with fs.open_input_file(f"{base}/{name}") as f:
                                index = IndexPart(f.read())
                    if index is None:
                        continue
                    some = batch.slice(lo, hi - lo)
                    ok, shard, offset, count = index.find(*(some.column(c).to_numpy().view(np.uint64) for c in (2, 3)))
                    keep = pa.array(ok)
                    yield pa.RecordBatch.from_arrays([some.column(0).filter(keep), some.column(1).filter(keep), pa.array(shard[ok]), pa.array(offset[ok]), pa.array(count[ok])], schema=found_schema)

        files = dict(self.files)
        out_schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

        def fetch(batches):
            fs, base = file_system(root)
            held, f, width = None, None, 2
            for batch in batches:
                shard, offset, count = (batch.column(c).to_numpy() for c in (2, 3, 4))
                sums, starts = np.zeros(batch.num_rows, np.int64), np.zeros(batch.num_rows, np.int64)
                for i in range(batch.num_rows):
                    if shard[i] != held:
                        if f is not None:
                            f.close()
                        held = shard[i]
                        f = fs.open_input_file(f"{base}/{files[int(held)][0]}")
                        head = f.read(16)
                        if head[:8] != _SHARD:
                            raise ValueError("not a shard")
                        width = int(np.frombuffer(head, "<u4", 1, 12)[0])
                    f.seek(16 + int(offset[i]) * width)
                    ids = np.frombuffer(f.read(int(count[i]) * width), f"<u{width}")
                    sums[i] = zlib.crc32(ids.astype("<u4", copy=False).tobytes())
                    starts[i] = files[int(held)][1] + offset[i]
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(starts), batch.column(4), pa.array(sums)], schema=out_schema)
            if f is not None:
                f.close()

        keyed = hashed_keys(keys.select("doc_id", "occurrence"), max(1, len(parts))).select("doc_id", "occurrence", "h", "g", "part")
        found = keyed.repartition("part").sortWithinPartitions("part").mapInArrow(look, "doc_id long, occurrence long, shard long, offset long, n_tokens long")
        return found.repartition("shard").sortWithinPartitions("shard", "offset").mapInArrow(fetch, "doc_id long, start long, n_tokens long, ids_crc32 long")


def runs(values: np.ndarray):
    cuts = np.flatnonzero(np.diff(values)) + 1
    return np.concatenate(([0], cuts))[: len(values)], np.append(cuts, len(values))[: max(len(values), 0) and len(cuts) + 1]


def write_store(docs: DataFrame, tokenizer_path: str, root: str | None = None, id_col: str = "doc_id", text_col: str = "text", end_id: int = 1, part_keys: int = 1 << 19) -> tuple[TokenStore, DataFrame]:
    """Write shards and index under ``root`` (default: the shared folder); the store and its record table."""
    spark = docs.sparkSession
    root = root or fresh_path(spark, "tokens")
    texts = in_batches(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    ordered = texts.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    records = materialize(ordered.mapInArrow(_write(root, tokenizer_path, end_id), "doc_id long, occurrence long, shard long, file string, offset long, n_tokens long"), "records")
    before, files, keys = 0, {}, 0
    for r in records.groupBy("shard", "file").agg(F.sum("n_tokens").alias("t"), F.count("*").alias("k")).orderBy("shard").collect():
        files[r["shard"]] = (r["file"], before)
        before += r["t"]
        keys += r["k"]
    n_parts = max(1, -(-keys // part_keys))
    parts = hashed_keys(records, n_parts).groupBy("part").applyInArrow(_build(root), "part long, part_file string, keys long, bytes long")
    made = [(r["part"], r["part_file"]) for r in materialize(parts, "parts").collect()]
    whole = dict.fromkeys(range(n_parts)) | dict(made)
    return TokenStore(spark, root, files, whole), records


def op10_token_store(spark, sf_dir: str) -> DataFrame:
    """Encode, write, then read every document back by its key."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    store, _ = write_store(docs, vocabulary_path())
    keys = docs.groupBy("doc_id").agg(F.count("*").alias("k")).select("doc_id", F.explode(F.expr("sequence(0L, k - 1L)")).alias("occurrence"))
    return store.read(keys)
