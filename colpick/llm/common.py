"""Helpers shared by the training-data operators."""

from __future__ import annotations

import re
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MASK64 = (1 << 64) - 1


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A table of the given directory with only the named columns."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet").select(*columns)


def durable(df: DataFrame) -> DataFrame:
    """``df`` written once to the cluster's checkpoint folder and read from there; see :func:`shared_folder`.

    The copy outlives any executor.
    """
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def release(spark: SparkSession) -> None:
    """Has the driver drop plans that no frame refers to any more: their shuffle files stay on disk until it collects its garbage."""
    spark.sparkContext._jvm.System.gc()


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the session names none, a temporary folder serves if everything runs
    in one process on this machine, as in tests; on a cluster that is an error.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        place = spark.conf.get("spark.checkpoint.dir", None)
        if not place and not re.match(r"local(\[|$)", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        sc.setCheckpointDir(place or tempfile.mkdtemp(prefix="colpick-checkpoint-"))
    return sc.getCheckpointDir()


def unused(name: str, *taken) -> str:
    """``name``, made longer until none of the given columns, or columns of frames, has it; case doesn't count."""
    known = {c.lower() for t in taken for c in (t.columns if isinstance(t, DataFrame) else [t])}
    while name.lower() in known:
        name += "_"
    return name


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Has the session send at most ``rows`` rows at a time to Python, from now on.

    A batch of the default 10,000 texts takes tens of megabytes at once, twice
    over in the executor's JVM while its buffers grow, and again in the worker.
    """
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= rows:
        spark.conf.set(name, str(rows))


def parts_for(df: DataFrame, rows: int) -> int:
    """A number of partitions of about ``rows`` rows each, at least the cluster's parallelism; counts ``df``."""
    return max(df.sparkSession.sparkContext.defaultParallelism, -(-df.count() // rows))


def text_key(text) -> F.Column:
    """128-bit digest of a text: equal texts share it, a null text counts as empty."""
    return F.unhex(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


#: Bits of one value of bitmap_construct_agg.
BITMAP = 32768


def marked(rows: DataFrame, needed: DataFrame, *keys, per_key: int = 16, most: int = 32 << 20) -> tuple[DataFrame, DataFrame] | None:
    """``rows`` in two: those that may have a key of ``needed``, and those that surely have none; nothing if the bitmaps would take over ``most`` bytes.

    ``keys`` are expressions over ``rows`` for the columns of ``needed``, in
    their order and types.  Each needed key sets one of ``per_key`` bits, so the
    first part has all rows that are needed and about one in ``per_key`` of the
    others; an exact join with ``needed`` then moves no more than these.
    """
    n = needed.count()
    if n * per_key > 8 * most:
        return None
    bits = BITMAP * max(1, -(-n * per_key // BITMAP))
    part, marks = unused("_part", rows), unused("_marks", rows)
    at = F.pmod(F.xxhash64(*needed.columns), F.lit(bits))
    maps = needed.select(at.alias("at")).groupBy(F.floor(F.col("at") / BITMAP).alias(part)).agg(F.bitmap_construct_agg(F.col("at") % BITMAP).alias(marks))
    place = F.pmod(F.xxhash64(*keys), F.lit(bits))
    byte = F.conv(F.hex(F.substr(F.col(marks), (F.floor(place % BITMAP / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("long")
    found = (F.floor(place / BITMAP) == F.col(part)) & (F.bit_get(byte, (place % 8).cast("int")) == 1)
    return rows.join(F.broadcast(maps), found, "left_semi"), rows.join(F.broadcast(maps), found, "left_anti")


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalise 64-bit values so that every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    out = np.full(max(n, 1), base, dtype=np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)[:n] if n else out[:0]


def inverse64(base: int) -> int:
    """The inverse of an odd number modulo 2**64."""
    return pow(base, -1, 1 << 64)


class Rolling:
    """Hashes of ranges of a sequence of 64-bit values, from one prefix sum.

    With prefix sums of x[i] * B**i, the hash of x[a:b] is their difference
    times B**-a, whatever the offset; all arithmetic wraps at 2**64.
    """

    def __init__(self, base: int):
        self.base, self.inverse = base | 1, inverse64(base | 1)
        self._up = self._down = np.empty(0, dtype=np.uint64)

    def _tables(self, n: int) -> None:
        if len(self._up) < n:
            size = max(n, 2 * len(self._up), 4096)
            self._up, self._down = powers(self.base, size), powers(self.inverse, size)

    def prefix(self, x: np.ndarray) -> np.ndarray:
        self._tables(len(x) + 1)
        out = np.zeros(len(x) + 1, dtype=np.uint64)
        np.cumsum(x * self._up[: len(x)], out=out[1:])
        return out

    def ranges(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix64((prefix[end] - prefix[start]) * self._down[start])

    def windows(self, prefix: np.ndarray, width: int) -> np.ndarray:
        n = len(prefix) - width
        if n <= 0:
            return np.empty(0, dtype=np.uint64)
        return mix64((prefix[width:] - prefix[:n]) * self._down[:n])


def chunks(texts: Iterable[str | None], limit: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose texts make up about ``limit`` characters each."""
    start = size = at = 0
    for at, text in enumerate(texts):
        size += len(text or "") + 1
        if size >= limit:
            yield start, at + 1
            start, size = at + 1, 0
    if size:
        yield start, at + 1


def portions(column: pa.Array, limit: int = 1 << 20) -> Iterator[list[str | None]]:
    """The texts of an Arrow column as lists of about ``limit`` bytes each, so that few are Python objects at a time."""
    if not len(column):
        return
    total = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 1)
    at = 0
    for end in np.unique(np.append(np.searchsorted(total, np.arange(limit, total[-1], limit)) + 1, len(column))).tolist():
        yield column.slice(at, end - at).to_pylist()
        at = end


def pieces(batches: Iterable[pa.RecordBatch], *sized: int, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batches cut by rows into slices of about ``limit`` bytes of the texts or binary values in the columns ``sized``.

    Memory that numbers, texts and sets took is given back after each batch: a
    worker outlives its task, and the next one would start on top of it.
    """
    for batch in batches:
        if not batch.num_rows:
            continue
        each = sum(pc.fill_null(pc.binary_length(batch.column(i)), 0).to_numpy(zero_copy_only=False).astype(np.int64) for i in sized) + 1
        total, at = np.cumsum(each), 0
        for end in np.unique(np.append(np.searchsorted(total, np.arange(limit, total[-1], limit)) + 1, len(total))).tolist():
            yield batch.slice(at, end - at)
            at = end
        del batch, each, total
        pa.default_memory_pool().release_unused()


def batch_of(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, (pa.Array, pa.ChunkedArray)) else pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)
