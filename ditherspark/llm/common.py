"""What the operators share: texts as byte buffers, bounded slices, working tables in the shared folder."""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one step of a vectorised kernel holds; its scratch arrays take some 40 times that.
SLICE_BYTES = 2 << 20
#: The same where executors have less to spare: the pipeline's stages run in the workers and beside the full heap of those before.
NARROW_BYTES = 1 << 20
#: The bytes that separate words everywhere here: space and \x09-\x0D.
SPACES = b"\x20\x09\x0a\x0b\x0c\x0d"
SPACE_LUT = np.zeros(256, bool)
SPACE_LUT[list(SPACES)] = True


def shared_folder(spark: SparkSession) -> str:
    """A new path below ``spark.checkpoint.dir``; where that is unset, one below /tmp is set for a
    single machine (tests), and a cluster is refused."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        jsc = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = jsc.get() if jsc.isDefined() else None
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines see")
        base = "file:///tmp/checkpoints"
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/llm-{uuid.uuid4().hex}"


#: Rows of a few numbers that one file of a working table should hold.
FILE_ROWS = 500_000


def written(df: DataFrame, name: str, rows: int | None = None) -> DataFrame:
    """``df`` stored as Parquet in the shared folder and read again: lineage ends here, any executor may be lost. With
    the expected number of narrow ``rows``, in as many files as these need and no more."""
    path = f"{shared_folder(df.sparkSession)}/{name}"
    (df if rows is None else df.coalesce(max(1, -(-rows // FILE_ROWS)))).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Rows of a few numbers that a join may send to the driver and broadcast.
BROADCAST_ROWS = 200_000


def merged(df: DataFrame, rows: int | None = None) -> DataFrame:
    """``df`` for a join by merging, unless it has few ``rows``. Spark takes the rows that explode makes for as many as it
    was given and files for as large as they are compressed, so by itself it broadcasts tables that the driver can't hold."""
    return df if rows is not None and rows <= BROADCAST_ROWS else df.hint("merge")


#: Rows whose 64-bit numbers a filter may hold in each worker, 8 bytes a row.
HELD_ROWS = 4_000_000


def among(rows: DataFrame, *on: str) -> Column:
    """True where the ``on`` columns are those of one of ``rows`` (at most ``HELD_ROWS``), and elsewhere only if their 64-bit
    hashes are the same. The numbers go to the workers, so what is filtered is not shuffled, however wide it is."""
    numbers = np.sort(rows.select(F.xxhash64(*on).alias("number")).toArrow()["number"].to_numpy())
    if not len(numbers):
        return F.lit(False)
    held = rows.sparkSession.sparkContext.broadcast(numbers)

    def there(number: pa.Array) -> pa.Array:
        asked = number.to_numpy(zero_copy_only=False)
        return pa.array(held.value[np.minimum(np.searchsorted(held.value, asked), len(held.value) - 1)] == asked)

    return F.arrow_udf(there, "boolean")(F.xxhash64(*on))


def free_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base += "_"
    return base


def row_hash(df: DataFrame):
    """A hash of all columns of a row; maps, which Spark doesn't hash, are left out."""
    from pyspark.sql.types import ArrayType, MapType, StructType

    def has_map(t) -> bool:
        inner = [t.elementType] if isinstance(t, ArrayType) else [f.dataType for f in t.fields] if isinstance(t, StructType) else []
        return isinstance(t, MapType) or any(map(has_map, inner))

    return F.xxhash64(*[F.col(f"`{f.name.replace('`', '``')}`") for f in df.schema if not has_map(f.dataType)])


def doc_crc(col: str = "doc_id"):
    """crc32 of the id as text, which fixes folds."""
    return F.crc32(F.col(col).cast("string").cast("binary"))


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and n+1 offsets into them; null counts as empty."""
    arr = texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts
    arr = pc.fill_null(arr.cast(pa.large_binary()), b"")
    if not len(arr):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    off = np.frombuffer(arr.buffers()[1], np.int64)[arr.offset : arr.offset + len(arr) + 1]
    data = np.frombuffer(arr.buffers()[2], np.uint8)[off[0] : off[-1]] if arr.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data, off - off[0]


def sliced(batch: pa.RecordBatch, column: str = "text", budget: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Consecutive slices of at most ``budget`` bytes of ``column``; a longer text stands alone, whole."""
    size = np.cumsum(pc.fill_null(pc.binary_length(batch[column]), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at, base = 0, 0
    while at < batch.num_rows:
        end = max(at + 1, int(np.searchsorted(size, base + budget, side="right")))
        yield batch.slice(at, end - at)
        at, base = end, int(size[end - 1])


def released() -> None:
    """Gives the machine back what is free in this process. Workers live on from task to task and from stage to stage, and
    allocators keep what the largest step took."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc
        trim(0)


def mapped(df: DataFrame, kernel: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str, column: str = "text", budget: int = SLICE_BYTES) -> DataFrame:
    """``df`` through a kernel that takes bounded slices. ``kernel()`` is called once a task, for its caches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = kernel()
        for batch in batches:
            released()
            for part in sliced(batch, column, budget):
                yield step(part)
        del step
        released()

    return df.mapInArrow(run, schema)


def strings(data: np.ndarray, offsets: np.ndarray) -> pa.Array:
    """Adjacent byte strings as an Arrow array without copying."""
    return pa.Array.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(data)])


def words(data: np.ndarray, offsets: np.ndarray, lower: bool = True) -> tuple[pa.Array, np.ndarray]:
    """Words of all texts as an Arrow array, and how many each text has."""
    if lower:
        upper = (data >= 65) & (data <= 90)
        data = data + (upper.astype(np.uint8) << 5)
    text = np.concatenate([data, np.array([32], np.uint8)])
    gap = SPACE_LUT[text]
    before = np.empty(len(text), bool)
    before[0] = True
    before[1:] = gap[:-1]
    first = np.zeros(len(text), bool)
    first[offsets[:-1][offsets[:-1] < len(data)]] = True
    start = np.flatnonzero(~gap & (before | first))
    stops = gap.copy()
    stops[offsets[1:]] = True
    stop_at = np.flatnonzero(stops)
    end = stop_at[np.searchsorted(stop_at, start, side="right")]
    counts = np.diff(np.searchsorted(start, offsets))
    lens = end - start
    off = np.zeros(len(start) + 1, np.int64)
    np.cumsum(lens, out=off[1:])
    keep = text[~gap]
    return strings(keep, off), counts
