"""What the operators of this package share: shared-folder tables, batch walks, vectorised hashing."""

from __future__ import annotations

import contextlib
import ctypes
import functools
import gc
import sys
import types
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from py4j.protocol import Py4JError
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.tables import materialize, release, shared_dir

__all__ = ["materialize", "release", "shared_dir"]

U = np.uint64
_MIX1, _MIX2 = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)
_BASE = 0x9E3779B97F4A7C15


def fresh_path(spark, name: str) -> str:
    return f"{shared_dir(spark)}/catchment-{name}-{uuid.uuid4().hex}"


def file_system(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def bitmap_bits(ids: int) -> int:
    """Bits of a bitmap for so many ids: eight for each, but 2**28 at most (4 million rows of 16 bytes to broadcast).

    Beyond 2**25 ids more and more rows pass a bitmap that should not; the exact join after it then does more of the work.
    """
    return 1 << min(28, max(16, (8 * max(1, ids) - 1).bit_length()))


def id_slots(ids: DataFrame, bits: int, column: str = "doc_id") -> DataFrame:
    """A bitmap of the ids' hashes as rows (w, bitmap): at most bits / 64 rows of 16 bytes, so it can be broadcast."""
    return ids.select(F.pmod(F.xxhash64(column), F.lit(bits)).alias("s")).groupBy(F.expr("s div 64").alias("_w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(s % 64 as int))")).alias("_bitmap"))


def slot_hit(rows: DataFrame, slots: DataFrame, bits: int, column: str = "doc_id") -> DataFrame:
    """The rows with _hit: false where the id is surely not among the ids of ``slots``. No row moves."""
    at = F.pmod(F.xxhash64(column), F.lit(bits))
    marked = rows.withColumn("_s", at).withColumn("_w", F.expr("_s div 64"))
    return marked.join(F.broadcast(slots), "_w", "left").withColumn("_hit", F.coalesce(F.expr("_bitmap & shiftleft(1L, cast(_s % 64 as int))") != 0, F.lit(False))).drop("_w", "_s", "_bitmap")


def without_ids(rows: DataFrame, gone: DataFrame, column: str = "doc_id") -> DataFrame:
    """The rows whose id is not in ``gone`` (a written table); only rows that a broadcast bitmap cannot clear meet the exact anti-join."""
    bits = bitmap_bits(gone.count())
    marked = slot_hit(rows, id_slots(gone, bits, column), bits, column)
    maybe = marked.filter("_hit").drop("_hit").join(gone.select(column), column, "left_anti")
    return marked.filter("not _hit").drop("_hit").unionByName(maybe)


def _stores() -> dict:
    holder = sys.modules.setdefault("_catchment_worker_store", types.ModuleType("_catchment_worker_store"))
    return holder.__dict__


def worker_store(name: str) -> dict:
    """A dictionary that lives in the Python worker until a task of an operator that doesn't keep it."""
    return _stores().setdefault(name, {})


def _trim() -> None:
    """Hand what Python has freed back to the system."""
    pa.default_memory_pool().release_unused()
    give = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if give:
        give(0)


def lean(*keep: str):
    """For the function of a task: drop what other operators keep in the worker, and hand freed memory back at the end.

    A worker serves one task after the other, of any operator; without this it holds the tables of all of
    them, and the heap of its largest task.
    """

    def around(run):
        @functools.wraps(run)
        def whole(batches):
            stores = _stores()
            for name in [k for k, v in stores.items() if isinstance(v, dict) and not k.startswith("__") and k not in keep]:
                del stores[name]
            try:
                yield from run(batches)
            finally:
                _trim()

        return whole

    return around


#: The least and the largest free share, in percent, of the driver's heap after ``shrink_driver``.
FREE = {"MinHeapFreeRatio": "15", "MaxHeapFreeRatio": "30"}


def shrink_driver(spark) -> None:
    """Give back what the driver no longer needs: garbage, unused heap, and memory that native code has freed.

    A JVM keeps its heap up to 70 % free after a collection, and the C library keeps what hundreds of threads
    have freed in arenas of their own. For this one collection the heap's bounds are those of ``FREE``, then they are again what they were; it still
    grows when it has to. A JVM without these switches only collects.
    """
    gc.collect()
    _trim()
    jvm = spark._jvm
    factory, named = jvm.java.lang.management.ManagementFactory, jvm.java.lang.Class.forName
    with contextlib.ExitStack() as after:
        with contextlib.suppress(Py4JError):
            bean = factory.getPlatformMXBean(named("com.sun.management.HotSpotDiagnosticMXBean"))
            for name, share in FREE.items():  # put back in the reverse order, so the least is never above the largest
                was = bean.getVMOption(name).getValue()
                bean.setVMOption(name, share)
                after.callback(bean.setVMOption, name, was)
        jvm.System.gc()
    with contextlib.suppress(Py4JError):
        call = next(m for m in named("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        given = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        call.invoke(factory.getPlatformMBeanServer(), given)


def hand_back(spark) -> None:
    """Collect the driver's and the executors' garbage, so that their heaps shrink to what they need: on executors a task on every core asks for it.

    A heap that one operator has grown stays as large under the workers of the next one; the machine holds both.
    """
    cores = spark.sparkContext.defaultParallelism
    spark.range(0, cores, 1, cores).select(F.reflect(F.lit("java.lang.System"), F.lit("gc")).alias("done")).write.format("noop").mode("append").save()
    shrink_driver(spark)


#: Bytes of a batch of rows between the JVM and a Python worker.
BATCH_BYTES = 1 << 22


def in_batches(rows: DataFrame) -> DataFrame:
    """The rows, with the session's Arrow batches bounded by bytes: texts vary from a word to megabytes, and both
    sides hold a batch several times over. A smaller bound that the session has is kept."""
    spark, key = rows.sparkSession, "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(key)) > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))
    return rows


def by_bytes(batches, column: int, most: int = 1 << 22):
    """Batches cut into parts of about ``most`` bytes of the text column; a longer text stands alone."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        for lo, hi in slices(sizes.tolist(), most):
            yield batch.slice(lo, hi - lo)


def column_bytes(array) -> list:
    """A string or binary Arrow array as a list of bytes (None for null)."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    return array.cast(pa.binary()).to_pylist()


def slices(sizes, most: int):
    """Cut consecutive items into ranges whose sizes sum to about ``most``; a larger item stands alone."""
    start, total = 0, 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield start, len(sizes)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    x = x ^ (x >> U(30))
    x = x * _MIX1
    x = x ^ (x >> U(27))
    x = x * _MIX2
    return x ^ (x >> U(31))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    store = worker_store("powers")
    if "p" not in store or len(store["p"]) < n:
        size = max(n, 1 << 20)
        inverse = pow(_BASE, -1, 1 << 64)
        for key, base in (("p", _BASE), ("q", inverse)):
            a = np.full(size, U(base))
            a[0] = U(1)
            store[key] = np.multiply.accumulate(a)
    return store["p"], store["q"]


def hashed_words(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Where the words between spaces begin, and their 64-bit hashes; runs of spaces count as one."""
    b = np.frombuffer(text, np.uint8)
    gaps = np.flatnonzero(b == 32)
    starts = np.concatenate(([0], gaps + 1))
    ends = np.concatenate((gaps, [len(b)]))
    real = ends > starts
    starts, ends = starts[real], ends[real]
    if not len(starts):
        return starts, np.empty(0, np.uint64)
    p, q = _powers(len(b) + 1)
    sums = np.empty(len(b) + 1, np.uint64)
    sums[0] = 0
    np.cumsum((b.astype(np.uint64) + U(1)) * p[: len(b)], out=sums[1:])
    return starts, mix((sums[ends] - sums[starts]) * q[starts] + (ends - starts).astype(np.uint64))


def hashed_texts(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of texts in a row, and where each text's words begin among them (one more entry at the end)."""
    starts, hashes = hashed_words(b" ".join(texts))
    begins = np.cumsum([0] + [len(t) + 1 for t in texts])
    return hashes, np.searchsorted(starts, begins)


def word_hashes(joined: bytes) -> np.ndarray:
    """64-bit hashes of the words of a text."""
    return hashed_words(joined)[1]


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
