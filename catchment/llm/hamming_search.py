"""Exact k nearest neighbours of binary codes by incremental multi-index hashing.

Codes are cut into 16-bit segments. If every segment has been probed up to radius r, any code not met yet
differs by more than r in each of the m segments, so by at least m (r + 1) in all: the search of a
query ends as soon as its k-th verified distance is at most m (r + 1) - 1. Radii grow by one until then. A
round probes the buckets at its radius: by their keys, or, where a segment has fewer occupied buckets than
the radius has keys, by picking those among the occupied ones.

Equal codes form one class that carries its k + 1 least ids (more can never be among the nearest), so a very
common code is one row. Classes are dealt into blocks of at most ``block`` by a hash, queries into groups of
``group``; every group meets every block once, and each hands on the k + 1 best classes of a query. The
final ranking is by (distance, id); the query itself is left out.

Odd input: a null vector is neither searched nor found; missing or null entries count as zero bits; a null id
is ignored; rows that repeat an id count once each; with fewer than k others all are returned; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SEGMENT = 16


def sign_code(vector: str, dims: int):
    """The sign bits of a vector column as an array of 64-bit words."""
    words = []
    for lo in range(0, dims, 64):
        bits = f"transform(sequence(0, {min(64, dims - lo) - 1}), i -> if(coalesce(get({vector}, i + {lo}), 0) > 0, shiftleft(1L, i), 0L))"
        words.append(F.expr(f"aggregate({bits}, 0L, (a, x) -> a | x)"))
    return F.when(F.col(vector).isNotNull(), F.array(*words))


def masks(r: int) -> np.ndarray:
    """All 16-bit values with r bits."""
    return np.array([sum(1 << i for i in c) for c in combinations(range(SEGMENT), r)], np.uint16)


class MultiIndex:
    """Segment tables of a block of codes (rows of 64-bit words)."""

    def __init__(self, codes: np.ndarray):
        self.codes = codes
        self.parts = codes.view("<u2").reshape(len(codes), -1)
        self.order, self.starts, self.values = [], [], []
        for s in range(self.parts.shape[1]):
            self.order.append(np.argsort(self.parts[:, s], kind="stable"))
            sizes = np.bincount(self.parts[:, s], minlength=1 << SEGMENT)
            self.starts.append(np.concatenate(([0], np.cumsum(sizes))))
            self.values.append(np.flatnonzero(sizes).astype(np.uint16))

    def distances(self, queries: np.ndarray, which: np.ndarray, found: np.ndarray) -> np.ndarray:
        return np.bitwise_count(queries[which] ^ self.codes[found]).sum(axis=1, dtype=np.int64)

    def _buckets(self, part: np.ndarray, s: int, mask: np.ndarray, r: int) -> tuple[np.ndarray, np.ndarray]:
        """(query, bucket) of a segment's occupied buckets at exactly radius r."""
        held = self.values[s]
        if len(held) < len(mask):
            q, at = np.nonzero(np.bitwise_count(part[:, None] ^ held[None, :]) == r)
            return q, held[at].astype(np.int64)
        keys = (part[:, None] ^ mask[None, :]).ravel().astype(np.int64)
        full = np.flatnonzero(self.starts[s][keys + 1] > self.starts[s][keys])
        return full // len(mask), keys[full]

    def _probe(self, parts: np.ndarray, r: int) -> tuple[np.ndarray, np.ndarray]:
        """(query, code) pairs that agree within exactly r bits in some segment."""
        mask, out = masks(r), []
        for s in range(parts.shape[1]):
            q, key = self._buckets(parts[:, s], s, mask, r)
            if not len(q):
                continue
            lo = self.starts[s][key]
            n = self.starts[s][key + 1] - lo
            stops = np.cumsum(n)
            at = np.repeat(lo - (stops - n), n) + np.arange(stops[-1])
            out.append(np.repeat(q, n) * len(self.codes) + self.order[s][at])
        pairs = np.unique(np.concatenate(out)) if out else np.empty(0, np.int64)
        return pairs // len(self.codes), pairs % len(self.codes)

    def search(self, queries: np.ndarray, heads: np.ndarray, copies: np.ndarray, k: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """For each query its best classes (rows of the block, distances) by (distance, head id), enough for k ids."""
        m, n = self.parts.shape[1], len(self.codes)
        parts = queries.view("<u2").reshape(len(queries), -1)
        best: list = [(np.empty(0, np.int64), np.empty(0, np.int64))] * len(queries)
        active = np.arange(len(queries))
        for r in range(SEGMENT + 1):
            if not len(active):
                break
            room = max(1, (1 << 20) // len(masks(r)))
            left = []
            for lo in range(0, len(active), room):
                some = active[lo : lo + room]
                q, c = self._probe(parts[some], r)
                d = self.distances(queries, some[q], c)
                cut = np.searchsorted(q, np.arange(len(some) + 1))
                for j, i in enumerate(some.tolist()):
                    codes, at = np.unique(np.concatenate((best[i][0], c[cut[j] : cut[j + 1]])), return_index=True)
                    dist = np.concatenate((best[i][1], d[cut[j] : cut[j + 1]]))[at]
                    order = np.lexsort((heads[codes], dist))[:k]
                    codes, dist = codes[order], dist[order]
                    best[i] = codes, dist
                    reach = np.searchsorted(np.cumsum(copies[codes]), k)
                    if len(codes) < n and (reach >= len(codes) or dist[reach] > m * (r + 1) - 1):
                        left.append(i)
            active = np.array(left, np.int64)
        return best


def nearest(rows: DataFrame, queries: DataFrame, k: int, words: int, block: int = 1 << 16, group: int = 4096) -> DataFrame:
    """(vec_id, rank, neighbor_id, distance) for (vec_id, code) queries against (vec_id, code) rows."""
    rows, queries = (x.filter("vec_id is not null and code is not null").select("vec_id", "code") for x in (rows, queries))
    first = Window.partitionBy("code").orderBy("vec_id")
    least = rows.withColumn("_n", F.row_number().over(first)).filter(F.col("_n") <= k + 1)
    classes = least.groupBy("code").agg(F.sort_array(F.collect_list("vec_id")).alias("ids"))
    total = classes.count()
    blocks = max(1, -(-total // block))
    asked = queries.select("code").distinct()
    left = classes.withColumn("block", F.pmod(F.xxhash64("code"), F.lit(blocks)))
    n_asked = asked.count()
    # as many pieces of work as four a core, as long as a piece keeps 128 queries; no more than needed where blocks abound
    wanted = -(-4 * rows.sparkSession.sparkContext.defaultParallelism // blocks)
    groups = max(1, -(-n_asked // group), min(wanted, n_asked // 128))
    right = asked.withColumn("part", F.pmod(F.xxhash64("code", F.lit(3)), F.lit(groups))).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    left = left.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    found_type = pa.struct([("d", pa.int64()), ("id", pa.int64())])

    def meet(mine: pa.Table, theirs: pa.Table) -> pa.Table:
        code_type = pa.list_(pa.int64())
        empty = pa.table({"code": pa.array([], code_type), "found": pa.array([], pa.list_(found_type))})
        if not mine.num_rows or not theirs.num_rows:
            return empty
        codes, asked_codes = (np.array(t.column("code").to_pylist(), np.int64).view(np.uint64) for t in (mine, theirs))
        ids = mine.column("ids").to_pylist()
        heads, copies = np.array([x[0] for x in ids]), np.array([len(x) for x in ids])
        out = []
        for c, d in MultiIndex(np.ascontiguousarray(codes)).search(np.ascontiguousarray(asked_codes), heads, copies, k + 1):
            pairs = sorted((int(y), i) for x, y in zip(c, d) for i in ids[x])[: k + 1]
            out.append([{"d": y, "id": i} for y, i in pairs])
        return pa.table({"code": pa.array(theirs.column("code").to_pylist(), code_type), "found": pa.array(out, pa.list_(found_type))})

    met = left.groupBy("block", "part").cogroup(right.groupBy("block", "part")).applyInArrow(meet, "code array<long>, found array<struct<d:long,id:long>>")
    best = met.groupBy("code").agg(F.slice(F.sort_array(F.flatten(F.collect_list("found"))), 1, k + 1).alias("found"))
    mine = queries.join(best, "code").select("vec_id", F.expr(f"slice(filter(found, x -> x.id != vec_id), 1, {k})").alias("found"))
    return mine.select("vec_id", F.posexplode("found").alias("rank", "f")).select("vec_id", (F.col("rank") + 1).alias("rank"), F.col("f.id").alias("neighbor_id"), F.col("f.d").alias("distance"))


def op5_exact_topk(spark, sf_dir: str, k: int = 10, dims: int = 64) -> DataFrame:
    """The 10 nearest sign codes of every vector whose id is divisible by 20, among all others."""
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", sign_code("embedding", dims).alias("code"))
    return nearest(rows, rows.filter("vec_id % 20 = 0"), k, -(-dims // 64))


SQL = {
    "op5_exact_topk": """
WITH codes AS (SELECT vec_id, list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END) AS b FROM embeddings),
pairs AS (
  SELECT q.vec_id, r.vec_id AS neighbor_id,
    list_sum(list_transform(list_zip(q.b, r.b), lambda p: CASE WHEN p[1] <> p[2] THEN 1 ELSE 0 END))::BIGINT AS distance
  FROM codes q JOIN codes r ON q.vec_id % 20 = 0 AND q.vec_id <> r.vec_id)
SELECT vec_id, rank::INT AS rank, neighbor_id, distance
FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY distance, neighbor_id) AS rank FROM pairs) WHERE rank <= 10
""",
}
