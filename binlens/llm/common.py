"""Shared plumbing of the training-data operators: shared storage, Arrow text access, fixed-size bitmaps.

Everything that must outlive one job goes to the folder named by ``spark.checkpoint.dir``: executors and
driver see it, so a lost executor costs only a re-read.  Nothing is kept in a machine-local folder.
"""

from __future__ import annotations

import atexit
import ctypes
import shutil
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text hashed at once; bounds the numpy temporaries of one Python worker (some 15 times as much).
SLICE_BYTES = 512 << 10


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one, removed at exit, only where the session names none
    (tests).  What is written to a named folder stays until its owner clears it: results are read from it lazily."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        folder = getattr(spark, "_binlens_shared", None)
        if folder is None:
            made = tempfile.mkdtemp(prefix="binlens-")
            atexit.register(shutil.rmtree, made, ignore_errors=True)
            folder = spark._binlens_shared = f"file://{made}"
    return folder.rstrip("/")


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: What workers keep between batches of one task, emptied at its end: functions without arguments.
KEPT: list[Callable[[], None]] = []


def give_back() -> None:
    """Empty what this worker has kept and return its free memory to the system."""
    for empty in KEPT:
        empty()
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        ctypes.CDLL(None).malloc_trim(0)


def narrow(df: DataFrame, run: Callable, schema) -> DataFrame:
    """``mapInArrow`` by a worker that gives its memory back when a task ends, as Spark keeps workers for later stages."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return df.mapInArrow(task, schema)


HOT_ROWS = 1024  # rows of one key from which on it is joined apart
HOT_KEYS = 1_000_000  # hot keys up to which they are broadcast


def join_hot(rows: DataFrame, facts: DataFrame, key: str, least: int = HOT_ROWS) -> DataFrame:
    """Left join with one row of facts for each key.  Keys of many rows are joined by broadcasting their facts, rows
    without a key meet nothing, and only the others are dealt out by key, so no task gathers a large group.  Give it
    rows that are written already, as they are read three times."""
    none = [F.lit(None).cast(t).alias(c) for c, t in facts.dtypes if c != key]
    hot = settle(rows.where(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("_n")).where(F.col("_n") >= least).select(key), "hot")
    apart = rows.where(F.col(key).isNull()).select("*", *none)
    if hot.count() > HOT_KEYS:
        return rows.where(F.col(key).isNotNull()).join(facts, key, "left").unionByName(apart)
    known = F.broadcast(facts.join(F.broadcast(hot), key, "left_semi"))
    warm = rows.join(F.broadcast(hot), key, "left_semi").join(known, key, "left")
    cold = rows.where(F.col(key).isNotNull()).join(F.broadcast(hot), key, "left_anti").join(facts, key, "left")
    return cold.unionByName(warm).unionByName(apart)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and its offsets (rows + 1); nulls become empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    if not len(column):
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    column = pc.fill_null(column.cast(pa.large_binary()), b"")
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.empty(0, np.uint8)
    return raw, off - off[0]


def slices(offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges that hold at most ``limit`` bytes each (a longer row stands alone)."""
    row, rows = 0, len(offsets) - 1
    while row < rows:
        end = int(np.searchsorted(offsets, offsets[row] + limit, "right")) - 1
        end = min(max(end, row + 1), rows)
        yield row, end
        row = end


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (two multiply-xorshift rounds); uint64 in and out."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


BITMAP_BITS = 24, 28  # least and most cells of a bitmap, as powers of two: 2 MB to 32 MB
_SEGMENT = 15  # cells of a segment, as a power of two


def bitmap_bits(keys: int) -> int:
    """Some 16 cells a key, within the bounds; beyond them a bitmap prunes less, and stays right."""
    return min(max(BITMAP_BITS[0], max(1, keys).bit_length() + 4), BITMAP_BITS[1])


class Bitmap:
    """A set sketch over 64-bit keys: never a false "absent", so it may only prune or order.

    It has at most 2^28 cells (32 MB) whatever the data; that is the bound under which it is broadcast.
    """

    def __init__(self, bits: np.ndarray):
        self.bits, self.shift = bits, np.uint64(64 - (len(bits) * 8).bit_length() + 1)

    def has(self, keys: np.ndarray) -> np.ndarray:
        at = keys.astype(np.uint64) >> self.shift
        return (self.bits[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 != 0


def bitmap_of(df: DataFrame, key: str) -> Bitmap:
    """Bitmap over a long column: positions are de-duplicated, then packed in segments of 4 KB by the executors."""
    size = bitmap_bits(df.count())
    at = df.select(F.shiftrightunsigned(F.col(key), 64 - size).alias("at")).distinct()

    def pack(batches):
        for segment, cells in runs(batches, lambda b: b.column(0).to_numpy() >> _SEGMENT):
            found = np.zeros(1 << _SEGMENT, bool)
            for c in cells:
                found[c.column(0).to_numpy() & ((1 << _SEGMENT) - 1)] = True
            packed = np.packbits(found, bitorder="little").tobytes()
            yield pa.RecordBatch.from_arrays([pa.array([segment], pa.int32()), pa.array([packed], pa.binary())], ["seg", "bits"])

    width = min(64, shuffle_width(df.sparkSession))
    dealt = at.repartition(width, F.shiftrightunsigned("at", _SEGMENT)).sortWithinPartitions("at")
    out = np.zeros(1 << (size - 3), np.uint8)
    for row in narrow(dealt, pack, "seg int, bits binary").collect():  # 32 MB at most, and a segment is whole in one partition
        out[row.seg << (_SEGMENT - 3) : (row.seg + 1) << (_SEGMENT - 3)] = np.frombuffer(row.bits, np.uint8)
    return Bitmap(out)


def runs(batches: Iterator[pa.RecordBatch], key: Callable) -> Iterator[tuple[int, list[pa.RecordBatch]]]:
    """Batches sorted by a whole-number key, cut up into one list of slices for each key."""
    now, held = None, []
    for b in batches:
        k = key(b)
        cut = np.concatenate([[0], np.flatnonzero(k[1:] != k[:-1]) + 1, [len(k)]])
        for i, j in zip(cut[:-1].tolist(), cut[1:].tolist()):
            if i < j:
                if held and int(k[i]) != now:
                    yield now, held
                    held = []
                now = int(k[i])
                held.append(b.slice(i, j - i))
    if held:
        yield now, held
