"""What the training-data operators share: scratch tables, Arrow text views, row numbers."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

WHITE = b" \t\n\x0b\x0c\r"

_LOCAL_ROOT: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """The folder the cluster shares, from spark.checkpoint.dir; where that is unset a temporary one, in local mode only."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _LOCAL_ROOT:
        _LOCAL_ROOT.append("file://" + tempfile.mkdtemp(prefix="topicgrid-"))
    return _LOCAL_ROOT[0]


class Scratch:
    """Intermediate Parquet tables below the shared folder.

    Writing a table cuts the lineage: what was written survives the loss of any executor. A table goes when
    ``drop`` is called, and whatever is left goes when the driver's Python ends, since lazy results may still
    read it until then.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_root(spark)}/topicgrid-{name}-{uuid.uuid4().hex}"
        atexit.register(self._remove, "")

    def table(self, df: DataFrame, name: str, few: bool = False) -> DataFrame:
        """Write and read again; ``few``: small rows after a shuffle, in at most four files a core."""
        if few:
            df = df.coalesce(4 * self.spark.sparkContext.defaultParallelism)
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        for name in names:
            self._remove(f"/{name}")

    def _remove(self, tail: str) -> None:
        jvm = self.spark.sparkContext._jvm
        if jvm is None or self.spark.sparkContext._jsc is None:
            return
        try:
            path = jvm.org.apache.hadoop.fs.Path(self.root + tail)
            path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
        except Exception as gone:  # the JVM ended first: nothing left to ask
            if tail:
                raise gone


def position(names: Sequence[str], wanted: str) -> int:
    """Where a column is: under just that name, else under one that differs in case."""
    if wanted in names:
        return list(names).index(wanted)
    for k, name in enumerate(names):
        if name.lower() == wanted.lower():
            return k
    raise ValueError(f"no column {wanted}; there are {', '.join(names)}")


def picked(df: DataFrame, **roles: str) -> DataFrame:
    """Only the columns that are named, under the names of their roles; all others may have any names, twice too."""
    at = {role: position(df.columns, name) for role, name in roles.items()}
    return df.toDF(*(f"c{k}" for k in range(len(df.columns)))).select(*(F.col(f"c{k}").alias(role) for role, k in at.items()))


@dataclass
class Passing:
    """A frame whose columns are called c0, c1, ... while an operator works, so that none clashes with one of the operator's own.

    ``at`` gives the place of each column that the operator reads. Columns named like an added one, in any case, are left out.
    """

    frame: DataFrame
    names: list[str]
    at: dict[str, int]
    added: tuple[str, ...]

    @classmethod
    def of(cls, df: DataFrame, reads: Sequence[str], added: Sequence[str] = ()) -> Passing:
        low = {a.lower() for a in added}
        read = [position(df.columns, r) for r in reads]
        kept = [k for k, c in enumerate(df.columns) if k in read or c.lower() not in low]
        frame = df.toDF(*(f"o{k}" for k in range(len(df.columns)))).select(*(F.col(f"o{k}").alias(f"c{j}") for j, k in enumerate(kept)))
        return cls(frame, [df.columns[k] for k in kept], {r: kept.index(k) for r, k in zip(reads, read, strict=True)}, tuple(added))

    def col(self, name: str):
        return F.col(f"c{self.at[name]}")

    @property
    def schema(self) -> StructType:
        """Of the passing columns, all nullable; the added ones may be appended."""
        return StructType([StructField(f.name, f.dataType, True) for f in self.frame.schema])

    def returned(self, df: DataFrame) -> DataFrame:
        """Under the names that the columns came with, then those added."""
        return df.toDF(*self.names, *self.added)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def utf8_view(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column as one array, and where each row begins and ends; null is empty."""
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    arr = pc.fill_null(arr.cast(pa.large_string()), "")
    if not len(arr):
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = arr.buffers()
    off = np.frombuffer(off, np.int64)[arr.offset : arr.offset + len(arr) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def blocks(batches: Iterator[pa.RecordBatch], text: str | int, most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that each has about ``most`` bytes of text, one row at least."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < n:
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + most, side="right")))
            yield batch.slice(at, to - at)
            at = to


def texts(arr: pa.Array) -> list[bytes]:
    """Rows as bytes; null is empty."""
    return pc.fill_null(arr.cast(pa.large_string()), "").cast(pa.large_binary()).to_pylist()


def release() -> None:
    """Give memory that a Python worker no longer uses back to the machine; workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # another C library has no such call
        ctypes.CDLL(None).malloc_trim(0)


def tidy(f):
    """A function for mapInArrow whose worker gives its memory back at the end of each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from f(batches)
        finally:
            release()

    return run


def mix64(x: np.ndarray) -> np.ndarray:
    """A fixed bijection of 64-bit words that spreads their bits (xor-shift and odd multipliers)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def held_out(doc_id: str = "doc_id"):
    """True for rows that no label may be learned from."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0, F.lit(True))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unplaced(df: DataFrame, key: str) -> DataFrame:
    """The same rows, with a BIGINT key that the optimiser takes for a new one.

    A side that was aggregated by a join's key is already placed by it, and then a hot key of the other side can't be
    split. Placed anew for the join, both sides can be split at run time.
    """
    return df.withColumn(key, F.col(key).bitwiseXOR(F.lit(0).cast("bigint")))


def small_enough(df: DataFrame, most: int) -> bool:
    """Whether a frame has at most that many rows; counts no further than one beyond."""
    return df.limit(most + 1).count() <= most
