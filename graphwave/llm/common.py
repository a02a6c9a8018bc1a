"""Shared parts of the text operators: Arrow mapping in bounded slices, word and shingle hashing in NumPy.

Every operator reads only an id column and a text column and returns fresh columns, so extra columns of the input, whatever
their names, neither matter nor pass through.
"""

from __future__ import annotations

import os
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: UTF-8 bytes of text that one slice holds at most, but for a longer single row.
SLICE_BYTES = 1 << 20


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select(*columns)


def shared_dir(spark: SparkSession) -> str:
    """Makes sure that checkpoint() has a folder: the cluster's own, or a scratch one where none is set."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        where = spark.conf.get("spark.checkpoint.dir", None)
        if where is None:
            where = f"file:///tmp/checkpoints/{os.getpid()}"
        sc.setCheckpointDir(where)
    return sc._jsc.sc().getCheckpointDir().get()


#: Rows that one task takes without strain; a smaller table is kept in one partition, and then needs no exchange.
TASK_ROWS = 15_000


def cut(df: DataFrame, rows: int | None = None, per: int = TASK_ROWS) -> DataFrame:
    """The same rows, written to the shared checkpoint folder, so that a lost executor costs no recomputation. rows: how many there are
    at most or about; then no more than rows / per files are written. A large table keeps all its partitions."""
    shared_dir(df.sparkSession)
    return (df if rows is None else df.coalesce(max(1, -(-rows // per)))).checkpoint(eager=True)


def row_count(df: DataFrame) -> int:
    """Rows of a written table, by one job over its partitions: no plan with an exchange for the driver to keep."""
    return df._jdf.queryExecution().toRdd().count()


def packed(df: DataFrame) -> tuple[DataFrame, int]:
    """A written table in as many partitions as its rows are worth (a few rows aren't dealt over hundreds of tasks), and its rows."""
    rows = row_count(df)
    n = max(1, -(-rows // TASK_ROWS))
    return (df.coalesce(n) if n < df._jdf.queryExecution().toRdd().getNumPartitions() else df), rows


def compact(df: DataFrame) -> DataFrame:
    return packed(df)[0]


def slices(batch: pa.RecordBatch, column: int, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Consecutive rows of a batch, each slice with at most `most` bytes of text or one row."""
    rows = batch.num_rows
    if rows == 0:
        return
    lengths = batch.column(column).nbytes
    if lengths <= most:
        yield batch
        return
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    ends = np.cumsum(sizes)
    start = 0
    while start < rows:
        base = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield batch.slice(start, stop - start)
        start = stop


#: Rows that Spark hands to Python at once, so that a batch of long texts stays small.
BATCH_ROWS = 2_000


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch size, if it is larger; it is a setting that may change while a session runs."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key, "10000")) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def arrow_map(df: DataFrame, schema: str, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], column: int = 1) -> DataFrame:
    """mapInArrow over bounded slices. make() runs once per task and returns the function for a slice."""

    def run(batches):
        fn = make()
        for batch in batches:
            for part in slices(batch, column):
                out = fn(part)
                if out is not None and out.num_rows:
                    yield out

    small_batches(df.sparkSession)
    return df.mapInArrow(run, schema)


def texts_of(column: pa.Array) -> list[str]:
    """Python strings, null as the empty string."""
    return [x or "" for x in column.to_pylist()]


# ---------------------------------------------------------------------------------------------------------------------
# hashing

_ODD = np.uint64(0x9E3779B97F4A7C15)
_MUL1 = np.uint64(0xBF58476D1CE4E5B9)
_MUL2 = np.uint64(0x94D049BB133111EB)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words; a fresh array."""
    x = x ^ (x >> np.uint64(30))
    x *= _MUL1
    x ^= x >> np.uint64(27)
    x *= _MUL2
    x ^= x >> np.uint64(31)
    return x


_POWERS = np.ones(1, dtype=np.uint64)
_INVERSES = np.ones(1, dtype=np.uint64)
_BASE = 0x5851F42D4C957F2D
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _POWERS, _INVERSES
    if len(_POWERS) < n:
        size = max(n, 1 << 20)
        ups, downs = np.full(size, _BASE, dtype=np.uint64), np.full(size, _BASE_INVERSE, dtype=np.uint64)
        ups[0] = downs[0] = 1
        _POWERS, _INVERSES = np.cumprod(ups), np.cumprod(downs)
    return _POWERS, _INVERSES


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of a byte array: polynomial prefix sums, then a finaliser. The same bytes give the same
    hash on every machine."""
    if len(starts) == 0:
        return np.zeros(0, dtype=np.uint64)
    ups, downs = _powers(len(data) + 1)
    sums = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * ups[: len(data)], out=sums[1:])
    out = (sums[ends] - sums[starts]) * downs[starts]
    return mix64(out + (ends - starts).astype(np.uint64) * _ODD)


_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def runs(flag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True."""
    edge = np.flatnonzero(np.diff(np.concatenate(([False], flag, [False])).view(np.int8)))
    return edge[::2], edge[1::2]


_PLAIN = np.ones(256, dtype=bool)
_PLAIN[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False


class Words:
    """Lower-cased words of a slice's texts, as 64-bit hashes with the row each word belongs to. Words are what stands between
    blanks, or, with letters_only, runs of letters and digits."""

    def __init__(self, texts: list[str], letters_only: bool = False):
        encoded = [t.lower().encode("utf-8", "surrogatepass") for t in texts]
        data = np.frombuffer(b"\n".join(encoded) + b"\n", dtype=np.uint8)
        starts, ends = runs(~(_PLAIN if letters_only else _SPACE)[data])
        limits = np.cumsum([len(e) + 1 for e in encoded])
        self.hash = span_hashes(data, starts, ends)
        self.row = np.searchsorted(limits, starts, side="right")
        self.count = np.bincount(self.row, minlength=len(texts)).astype(np.int64)
        self.first = np.concatenate(([0], np.cumsum(self.count)))  # word range of row i: first[i] .. first[i + 1]


def shingles(words: Words, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, row and starting word of every window of k words; a row of 1 to k - 1 words has one window of all of them."""
    n = len(words.hash)
    if n == 0:
        z = np.zeros(0, dtype=np.int64)
        return np.zeros(0, dtype=np.uint64), z, z
    acc = np.zeros(n, dtype=np.uint64)
    room = words.first[words.row + 1] - np.arange(n)  # words left in the row, this one included
    for j in range(k):
        inside = room > j
        h = np.zeros(n, dtype=np.uint64)
        h[: n - j] = words.hash[j:]
        acc = np.where(inside, acc * np.uint64(0xD6E8FEB86659FD93) + h + np.uint64(j + 1), acc)
    acc = mix64(acc)
    at = np.arange(n) - words.first[words.row]
    keep = (room >= k) | ((at == 0) & (words.count[words.row] < k))
    where = np.flatnonzero(keep)
    return acc[where], words.row[where], at[where]
