"""Shared helpers of the training-data operators: work folder, table cuts, byte buffers."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: The white space of every word definition here: blank and the controls 9 to 13.
SPACE = "[\\x20\\x09-\\x0D]"
WORD = "[^\\x20\\x09-\\x0D]+"


def shared_folder(spark: SparkSession) -> str:
    """Folder that the driver and all executors see, from spark.checkpoint.dir.

    Unset on a local master (tests): a temporary folder. Unset on a cluster: a
    subfolder of the warehouse, never a machine-local path.
    """
    conf = spark.sparkContext.getConf()
    base = conf.get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return f"file://{tempfile.mkdtemp(prefix='llm-work-')}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_llm_work"


class Workspace:
    """Tables of one operator call in the shared folder; each table cuts the lineage."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root, self._n = spark, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}", 0

    def next(self) -> int:
        """A number for a table's name."""
        self._n += 1
        return self._n

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str, **options: str) -> DataFrame:
        df.write.mode("overwrite").options(**options).parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, *names: str) -> None:
        jvm = self.spark._jvm
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(self.path(name))
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


    def keep(self, *names: str) -> None:
        """Drop all tables but these."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.root)
        files = path.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if files.exists(path):
            self.drop(*{str(x.getPath().getName()) for x in files.listStatus(path)} - set(names))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def text_or_empty() -> F.Column:
    return F.coalesce(F.col("text"), F.lit(""))


def fold(column: F.Column, modulus: int) -> F.Column:
    """crc32 of an id's decimal text, modulo a number: the split into folds."""
    return F.pmod(F.crc32(column.cast("string").cast("binary")), F.lit(modulus).cast("long"))


def blocks(values: list, weights: list[int], most: int) -> Iterator[slice]:
    """Cut a batch into runs of at most `most` bytes; a longer value stands alone."""
    start, total = 0, 0
    for i, w in enumerate(weights):
        if i > start and total + w > most:
            yield slice(start, i)
            start, total = i, 0
        total += w
    if start < len(values):
        yield slice(start, len(values))


#: What empties the tables that a worker process keeps between tasks of one kind.
KEPT: list[Callable[[], None]] = []


def give_back() -> None:
    """Return this process's freed memory to the system, which glibc and Arrow would keep."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def tidy(run: Callable, keep: bool = False) -> Callable:
    """A task's function that leaves its worker small, since workers live on into the next stages; keep: tables of `KEPT` stay for the next task."""

    def out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            if not keep:
                for empty in KEPT:
                    empty()
            give_back()

    return out


def schema(**fields: str) -> T.StructType:
    return T._parse_datatype_string(", ".join(f"{k} {v}" for k, v in fields.items()))


# -- hashing of words and word windows on whole byte buffers --

_U = np.uint64


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A strong 64-bit finaliser, elementwise."""
    x = x + _U((salt * 0xD1B54A32D192ED03 + 0x632BE59BD9B4E019) & (2**64 - 1))
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_ODD = _U(0x9FB21C651E98DF25)
_LOW_BYTES = np.array([(1 << (8 * k)) - 1 for k in range(9)], _U)


def word_codes(buffer: np.ndarray, starts: np.ndarray, ends: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit code of each word: its length, then eight bytes at a time, each through `mix`.

    No sum or polynomial: what differs early can't be cancelled by what comes later. Codes
    of two salts are independent, so both together are a 128-bit fingerprint.
    """
    n = ends - starts
    padded = np.concatenate((buffer, np.zeros(8, np.uint8)))
    eight = np.ndarray(len(buffer) + 1, "<u8", padded.data, strides=(1,))  # the eight bytes from each place on
    code = mix(mix(n.astype(_U), salt) ^ (eight[starts] & _LOW_BYTES[np.minimum(n, 8)]))
    left, at = np.flatnonzero(n > 8), 8
    while len(left):
        code[left] = mix((code[left] * _ODD) ^ (eight[starts[left] + at] & _LOW_BYTES[np.minimum(n[left] - at, 8)]))
        at += 8
        left = left[n[left] > at]
    return code


def window_codes(codes: np.ndarray, size: int) -> np.ndarray:
    """A 64-bit code of each run of `size` codes, joined two by two through `mix` in runs of 1, 2, 4 and so on."""
    if len(codes) < size:
        return codes[:0]
    out, done, run, width = None, 0, codes, 1
    while True:
        if size & width:
            part = run[done : len(codes) - size + done + 1]
            out = part if out is None else mix(out * _ODD + part, size)
            done += width
        if done == size:
            return mix(out, size)
        run = mix(run[: len(run) - width] * _ODD + run[width:], width)
        width *= 2


def word_spans(buffer: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words of a byte buffer; the separators are those of SPACE and byte 0xFF."""
    gap = (buffer == 32) | ((buffer >= 9) & (buffer <= 13)) | (buffer == 255)
    edge = np.diff(np.concatenate(([True], gap, [True])).astype(np.int8))
    return np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)


def gather_spans(buffer: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The concatenation of the spans of a buffer."""
    ends = np.cumsum(lengths)
    if not len(ends):
        return buffer[:0]
    at = np.repeat(starts - (ends - lengths), lengths)
    at += np.arange(ends[-1])
    return buffer[at]


def running_before(df: DataFrame, ws: Workspace, name: str, order: list, value: F.Column, out: str) -> DataFrame:
    """Add `out`, the sum of `value` over all rows before each row in an order, without one global window.

    Rows are range-partitioned and written once; only one sum a part goes to the driver.
    """
    spark = df.sparkSession
    rows = df.withColumn("_v", value.cast("long")).repartitionByRange(*order).sortWithinPartitions(*order)
    rows = ws.save(rows.withColumn("_part", F.spark_partition_id()), name)
    sums = sorted((r["_part"], r["s"]) for r in rows.groupBy("_part").agg(F.sum("_v").alias("s")).collect())
    offsets, total = [], 0
    for part, s in sums:
        offsets.append((part, total))
        total += s
    before = F.broadcast(spark.createDataFrame(offsets, schema(_part="int", _off="long")))
    w = W.partitionBy("_part").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    return rows.join(before, "_part").withColumn(out, F.col("_off") + F.coalesce(F.sum("_v").over(w), F.lit(0))).drop("_v", "_off")
