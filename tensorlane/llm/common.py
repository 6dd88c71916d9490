"""Shared plumbing: durable scratch tables, global row numbers, byte-level hashing."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: ASCII white space: space, and tab to carriage return.
SPACE_BYTES = b"\x20\x09\x0a\x0b\x0c\x0d"
#: Rows in an Arrow batch; with whole documents in a row, thousands would be hundreds of MB.
ARROW_ROWS = 1000

_local_base: str | None = None


def shared_base(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``).

    Where it is unset, a temporary folder is used, on a local master only.
    """
    global _local_base
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if _local_base is None:
        _local_base = tempfile.mkdtemp(prefix="llm-scratch-")
        atexit.register(shutil.rmtree, _local_base, ignore_errors=True)
    return f"file://{_local_base}"


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{shared_base(spark)}/{label}-{uuid.uuid4().hex}"


#: Whether the shuffles of a query are deleted as soon as it ends; else they wait for the driver's garbage collection.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def write_table(df: DataFrame, path: str) -> None:
    """Write ``df`` to ``path`` and delete the shuffles of this write, which nothing reads again."""
    conf = df.sparkSession.conf
    was = conf.get(CLEANUP, None)
    conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        conf.unset(CLEANUP) if was is None else conf.set(CLEANUP, was)


def written(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it again: its lineage ends there."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    write_table(df, path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def drop_written(*tables: DataFrame) -> None:
    """Delete tables made by :func:`written` that nothing reads any more."""
    for df in tables:
        path = getattr(df, "_scratch", None)
        if path:
            spark = df.sparkSession
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


#: A key that holds more than one in so many rows is looked up in a table that all workers get; there are fewer such keys than this.
HEAVY_KEYS = 10_000


def counted(df: DataFrame, label: str, count: str) -> DataFrame:
    """``written``, with the sum and the maximum of a column of counts taken on the way."""
    seen = Observation()
    out = written(df.observe(seen, F.sum(count).alias("rows"), F.max(count).alias("most")), label)
    out._counts = (seen.get.get("rows") or 0, seen.get.get("most") or 0)
    return out


def join_by_count(left: DataFrame, right: DataFrame, on: str | list[str], count: str, how: str = "inner") -> DataFrame:
    """``left`` joined with ``right`` (see ``counted``), which has one row a key and the number of the left's rows in column ``count``.

    The few keys with many rows would meet in one task each: they are broadcast, a list whose length is bounded
    whatever the sizes of the tables.  All other rows are joined as Spark sees fit.
    """
    rows, most = right._counts
    limit = max(rows // HEAVY_KEYS, 1000)
    if most <= limit:
        return left.join(right, on, how)
    heavy = F.col(count) > limit
    hot = F.broadcast(right.filter(heavy))
    rest = left.join(F.broadcast(right.filter(heavy).select(on)), on, "left_anti").join(right.filter(~heavy), on, how)
    return left.join(hot, on).unionByName(rest)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_batches(spark: SparkSession) -> None:
    """Keep Arrow batches of whole documents small (a run-time setting of the session)."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > ARROW_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))


def utf8(column: str | Column) -> Column:
    """The bytes of a text, none for null."""
    c = F.col(column) if isinstance(column, str) else column
    return F.coalesce(c.cast("binary"), F.lit("").cast("binary"))


def numbered(df: DataFrame, order: list[str], label: str, name: str = "row_number") -> tuple[DataFrame, int]:
    """``df`` with a gapless global row number from 0 in the order given, and the row count.

    Range partitioning and one narrow pass number the rows inside each partition; the only
    thing that reaches the driver is a count for each partition.  Rows that tie in ``order``
    are numbered in any order, so give enough columns to make ties interchangeable.
    """
    spark = df.sparkSession
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    placed = written(
        df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()),
        label,
    )
    part = F.shiftright("_at", 33)
    counts = sorted((r["p"], r["n"]) for r in placed.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    first, total = [], 0
    for p, c in counts:
        first.append((p, total))
        total += c
    starts = spark.createDataFrame(first or [(0, 0)], "_p long, _first long")
    out = placed.join(F.broadcast(starts), part == F.col("_p")).withColumn(
        name, F.col("_first") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    )
    return out.drop("_at", "_p", "_first"), total


# -- hashing of byte ranges ---------------------------------------------------------------

_SEGMENT = 1 << 20
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))
_BASE = 0x9E3779B97F4A7C15


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection on 64-bit words that spreads every bit (the splitmix finaliser)."""
    x = x ^ (x >> np.uint64(30))
    x = x * _MIX[0]
    x ^= x >> np.uint64(27)
    x *= _MIX[1]
    x ^= x >> np.uint64(31)
    return x


def _powers(base: int, n: int) -> np.ndarray:
    p = np.full(n, base, np.uint64)
    p[0] = 1
    return np.multiply.accumulate(p)


class RangeHash:
    """64-bit hashes of byte ranges of a buffer from prefix sums of a polynomial.

    ``fold`` maps bytes to bytes first (for instance to lower case).
    """

    _tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def __init__(self, fold: np.ndarray | None = None, seed: int = 7):
        values = np.random.default_rng(seed).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.values = values if fold is None else values[fold]

    @classmethod
    def tables(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        have = max(cls._tables, default=0)
        if have < n:
            cls._tables.clear()
            cls._tables[n] = (_powers(_BASE, n), _powers(pow(_BASE, -1, 1 << 64), n))
            have = n
        return cls._tables[have]

    def _terms(self, data: np.ndarray) -> np.ndarray:
        return self.values[data]

    def prefix(self, data: np.ndarray) -> np.ndarray:
        up, _ = self.tables(max(_SEGMENT, len(data) + 1))
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self._terms(data) * up[: len(data)], out=out[1:])
        return out

    def ranges(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        _, down = self.tables(max(_SEGMENT, len(prefix)))
        return mix((prefix[end] - prefix[start]) * down[start])

    def every(self, prefix: np.ndarray, width: int) -> np.ndarray:
        """``ranges`` of all ranges of ``width``, without looking up places."""
        n = len(prefix) - width
        _, down = self.tables(max(_SEGMENT, len(prefix)))
        return mix((prefix[width:] - prefix[:n]) * down[:n])


def lower_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    t[65:91] += 32
    return t


class Words:
    """Words of many documents as ranges of one buffer, with a 64-bit hash each."""

    def __init__(self, word_byte: np.ndarray, fold: np.ndarray | None = None):
        self.word_byte = word_byte
        self.hash = RangeHash(fold)

    def of(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all words in order, and the index of each document's first word (one more at the end)."""
        n = len(data)
        if not n:
            return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
        inside = self.word_byte[data]
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        start = inside.copy()
        start[1:] &= ~inside[:-1] | edge[1:n]
        end = inside.copy()
        end[:-1] &= ~inside[1:] | edge[1:n]
        starts, ends = np.flatnonzero(start), np.flatnonzero(end) + 1
        out = np.empty(len(starts), np.uint64)
        k = 0
        while k < len(starts):  # segments keep the tables of powers small, however long the buffer is
            at = starts[k]
            stop = max(k + 1, int(np.searchsorted(ends, at + _SEGMENT, "right")))
            prefix = self.hash.prefix(data[at : ends[stop - 1]])
            out[k:stop] = self.hash.ranges(prefix, starts[k:stop] - at, ends[k:stop] - at)
            k = stop
        return out, np.searchsorted(starts, offsets)


def buffers(column) -> tuple[np.ndarray, np.ndarray]:
    """Data and offsets of an Arrow binary column without nulls, offsets from 0."""
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    wide = np.int64 if "large" in str(column.type) else np.int32
    _, off, data = column.buffers()
    o = np.frombuffer(off, wide)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    d = np.frombuffer(data, np.uint8)[o[0] : o[-1]] if data is not None else np.zeros(0, np.uint8)
    return d, o - o[0]


def document_blocks(batches, text: str, most_bytes: int):
    """Slices of Arrow batches with about ``most_bytes`` of text each; one document is never split."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        _, off = buffers(batch.column(batch.schema.get_field_index(text)))
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(off, off[at] + most_bytes, "right")) - 1)
            yield batch.slice(at, to - at)
            at = to
