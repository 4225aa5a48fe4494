"""Best-fit packing of token sequences, hierarchical: partitions pack locally, underfull bins merge up a tree.

Documents are encoded, an end id is appended, and only what is longer than a sequence is cut. The pieces
with their ids are dealt anew by a hash, so that every node has long and short ones whatever lay together in the input. Every
node packs its pieces best-fit (longest first, tightest gap) and puts the ids of each bin in a row. Bins at least ``full_at`` full
stay as they are; the others become items of the next round, in which groups of ``fan`` nodes pack
their bins best-fit once more, until one node is left. A node hands up at most ``carry`` bins (the
emptiest), or as many as there are nodes if these are more. That is no cut: after a best-fit at most one bin is half full or
less, one of two bins that fit together must be, and so every such bin rises and finds as many partners as could take one.
Rows that move between rounds are bins without ids; a sequence's ids move once more only where bins of several nodes make it up.

Ids are little-endian, two bytes each where the vocabulary has no id above 65,535, else four.

Odd input: null text is the end id alone; a null or repeated id keeps its rows, each a document of
its own; an empty table gives an empty result; columns other than id and text are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, in_batches, lean, materialize, release
from .tokens import encoded, encoder

#: Ids of a node, about: its task holds them.
NODE_IDS = 1 << 24
#: Bytes of ids of a batch that leaves a node, about.
BATCH_IDS = 1 << 22
PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long, ids binary"


def best_fit(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Longest first into the fullest bin that has room: each item's bin and offset, each bin's fill."""
    bins = np.zeros(len(lengths), np.int64)
    offsets = np.zeros(len(lengths), np.int64)
    fills: list[int] = []
    by_gap: list[list[int]] = [[] for _ in range(capacity + 1)]
    gaps = 0
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        fitting = gaps >> n
        if fitting:
            gap = n + (fitting & -fitting).bit_length() - 1
            b = by_gap[gap].pop()
            if not by_gap[gap]:
                gaps &= ~(1 << gap)
        else:
            gap, b = capacity, len(fills)
            fills.append(0)
        bins[i], offsets[i] = b, fills[b]
        fills[b] += n
        by_gap[gap - n].append(b)
        gaps |= 1 << (gap - n)
    return bins, offsets, np.array(fills, np.int64)


def _cut(path: str, end_id: int, capacity: int):
    """Pieces of documents: (doc_id, piece, start, length, ids_crc32, ids)."""
    schema = pa.schema([(n, pa.int32() if n == "piece" else pa.int64()) for n in ("doc_id", "piece", "start", "length", "ids_crc32")] + [("ids", pa.binary())])

    @lean("encoders")
    def run(batches):
        for batch in by_bytes(batches, 1):
            rows: list[list] = [[] for _ in range(5)]
            ids, sizes = encoded(batch.column(1), path, end_id)
            ids = ids.astype("<u4", copy=False)
            at = 0
            for doc, n in zip(batch.column(0).to_pylist(), sizes.tolist()):
                for k, start in enumerate(range(0, n, capacity)):
                    size = min(capacity, n - start)
                    for column, value in zip(rows, (doc, k, start, size, zlib.crc32(ids[at + start : at + start + size]))):
                        column.append(value)
                at += n
            narrow = ids.astype("<u2" if max(len(encoder(path).ends) - 1, end_id) < 1 << 16 else "<u4")
            # pieces lie in a row among the ids
            stops = np.cumsum([0, *rows[3]], dtype=np.int64) * narrow.itemsize
            texts = pa.Array.from_buffers(pa.binary(), len(rows[3]), [None, pa.py_buffer(stops.astype(np.int32)), pa.py_buffer(narrow)])
            yield pa.RecordBatch.from_arrays([*[pa.array(c, f.type) for c, f in zip(rows, schema)], texts], schema=schema)

    return run


def _local(capacity: int):
    """Best-fit over a partition's pieces; adds (node, bin, place, fill), and a bin's ids stand in the row of its first piece."""

    @lean()
    def run(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held)
        keys = table.drop_columns("ids")
        order = pc.sort_indices(keys, sort_keys=[("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])
        bins, offsets, fills = best_fit(keys.column("length").take(order).to_numpy(), capacity)
        by_bin = np.lexsort((offsets, bins))
        rows = order.to_numpy()[by_bin]
        keys, bins, offsets = keys.take(pa.array(rows)), bins[by_bin], offsets[by_bin]
        node = np.full(len(bins), TaskContext.get().partitionId(), np.int64)
        for name, values in (("node", node), ("bin", bins), ("place", offsets), ("fill", fills[bins])):
            keys = keys.append_column(name, pa.array(values))
        ids = table.column("ids").to_pylist()
        del table, held
        begins = [*np.flatnonzero(offsets == 0).tolist(), len(rows)]
        rows = rows.tolist()
        start, texts, amount = 0, [], 0
        for lo, hi in zip(begins, begins[1:]):
            texts += [b"".join([ids[r] for r in rows[lo:hi]]), *[None] * (hi - lo - 1)]
            amount += len(texts[lo - start])
            if amount >= BATCH_IDS or hi == len(rows):
                yield from keys.slice(start, hi - start).append_column("ids", pa.array(texts, pa.binary())).combine_chunks().to_batches()
                start, texts, amount = hi, [], 0

    return run


def _merge(capacity: int, full_at: int, carry: int):
    def run(table: pa.Table) -> pa.Table:
        order = table.sort_by([("node", "ascending"), ("bin", "ascending")])
        fills = order.column("fill").to_numpy()
        bins, offsets, totals = best_fit(fills, capacity)
        up = np.flatnonzero(totals < full_at)
        up = up[np.argsort(totals[up], kind="stable")][:carry]
        rises = np.zeros(len(totals), bool)
        rises[up] = True
        return pa.table({"node": order.column("node"), "bin": order.column("bin"), "fill": order.column("fill"), "parent": order.column("parent"), "parent_bin": bins, "shift": offsets, "parent_fill": totals[bins], "rises": rises[bins]})

    return run


def pack(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", end_id: int = 1, capacity: int = 4096, full_share: float = 0.998, fan: int = 8, carry: int = 65_536, node_pieces: int = 1 << 16) -> DataFrame:
    """One row a piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset, sequence_fill, sequence_ids.

    ``sequence_ids`` is the whole sequence, all ids of its pieces in order, in the row of its first piece (offset 0), null in the others.
    """
    texts = in_batches(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    cut = materialize(texts.mapInArrow(_cut(tokenizer_path, end_id, capacity), PIECE), "cut", compression="zstd")
    count, ids = cut.agg(F.count("*"), F.coalesce(F.sum("length"), F.lit(0))).first()
    nodes = lowest = max(1, -(-count // node_pieces), -(-ids // NODE_IDS))
    dealt = cut.repartition(nodes, F.xxhash64("doc_id", "piece", "start", "ids_crc32"))
    pieces = materialize(dealt.mapInArrow(_local(capacity), PIECE.replace(", ids binary", ", node long, bin long, place long, fill long, ids binary")), "pieces", compression="zstd")
    release(cut)
    full_at = int(capacity * full_share)
    items = pieces.filter(f"place = 0 and fill < {full_at}").select("node", "bin", "fill")
    kind = "node long, bin long, fill long, parent long, parent_bin long, shift long, parent_fill long, rises boolean"
    levels = []
    while True:
        nodes = -(-nodes // fan)
        merged = materialize(items.withColumn("parent", F.expr(f"node div {fan}")).groupBy("parent").applyInArrow(_merge(capacity, full_at, max(carry, lowest)), kind), "bins")
        levels.append(merged)
        if nodes <= 1:
            break
        items = merged.filter("shift = 0 and rises").select(F.col("parent").alias("node"), F.col("parent_bin").alias("bin"), F.col("parent_fill").alias("fill"))
    final = None
    for level in range(len(levels), 0, -1):
        here = levels[level - 1].select("node", "bin", "fill", "parent", "parent_bin", "shift", "parent_fill")
        own = F.expr(f"shiftleft({level}L, 58) + shiftleft(parent, 34) + parent_bin")
        if final is None:
            final = here.select("node", "bin", "fill", own.alias("sequence_id"), "shift", F.col("parent_fill").alias("sequence_fill"))
        else:
            above = final.select(F.col("node").alias("parent"), F.col("bin").alias("parent_bin"), F.col("sequence_id").alias("s"), F.col("shift").alias("more"), F.col("sequence_fill").alias("f"))
            final = here.join(above, ["parent", "parent_bin"], "left").select("node", "bin", "fill", F.coalesce("s", own).alias("sequence_id"), (F.col("shift") + F.coalesce("more", F.lit(0))).alias("shift"), F.coalesce("f", "parent_fill").alias("sequence_fill"))
    # all bins but one of a sequence are half full or less, and a node has one such bin: two rows a node at most
    joined = final.filter("sequence_fill > fill").drop("fill")
    placed = pieces.join(F.broadcast(joined), ["node", "bin"], "left").withColumn("offset", F.col("place") + F.coalesce("shift", F.lit(0)))
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "sequence_fill", "sequence_ids"]
    alone = placed.filter("shift is null").withColumns({"sequence_id": F.expr("shiftleft(node, 34) + bin"), "sequence_fill": F.col("fill"), "sequence_ids": F.col("ids")})
    several = placed.filter("shift is not null")
    parts = several.filter("place = 0").groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("shift", "ids"))).alias("parts"))
    whole = parts.select("sequence_id", F.expr("aggregate(parts, cast('' as binary), (a, p) -> concat(a, p.ids))").alias("whole"))
    several = several.join(whole, "sequence_id").withColumn("sequence_ids", F.when(F.col("offset") == 0, F.col("whole")))
    return alone.select(columns).unionByName(several.select(columns))


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op7_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), vocabulary_path())
