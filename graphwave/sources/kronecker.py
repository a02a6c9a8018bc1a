"""Synthetic Kronecker graphs by portable integer arithmetic.

Edge i draws one quadrant for each bit of its two ends, from the most significant bit on. The draws are congruences modulo the prime
2^31 - 1, so every product stays below 2^63 and any SQL engine makes the same graph. Quadrant shares are 57, 19, 19 and 5 per cent.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Fixed values of the generator.
PRIME = 2147483647
ROUNDS = ((48271, 11), (69621, 1013), (16807, 7919))
SHARES = (57, 76, 95)
SEED_STEP = 1000003


def draws(i: np.ndarray, b: int, seed: int) -> np.ndarray:
    """A number from 0 to 99 for bit b of each edge."""
    x = (i * 64 + (b + seed * SEED_STEP)) % PRIME
    for a, c in ROUNDS:
        x = (x * a + c) % PRIME
        x = (x * x + x) % PRIME
    return x % 100


def ends(i: np.ndarray, scale: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """u and v of the edges with these numbers."""
    u, v = np.zeros(len(i), dtype=np.int64), np.zeros(len(i), dtype=np.int64)
    one, two, three = SHARES
    for b in range(scale):
        r = draws(i, b, seed)
        u = u << 1 | (r >= two)
        v = v << 1 | (((r >= one) & (r < two)) | (r >= three))
    return u, v


def kronecker_edges(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 42, relabel: int | None = None, partitions: int | None = None) -> DataFrame:
    """(u, v) of edge_factor * 2^scale tuples, duplicates and self-loops included. relabel: an odd factor that permutes ids.

    A column expression would repeat each draw's chain of congruences for every use of it, beyond what code generation takes; so batches
    of edge numbers are worked out as arrays."""
    n = 1 << scale

    def run(batches):
        for batch in batches:
            u, v = ends(np.asarray(batch.column(0), dtype=np.int64), scale, seed)
            if relabel is not None:
                u, v = (u * relabel + 17) % n, (v * relabel + 17) % n
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])

    ids = spark.range(0, edge_factor * n, 1, partitions) if partitions else spark.range(edge_factor * n)
    return ids.mapInArrow(run, "u long, v long")


def kronecker_sql(scale: int, edge_factor: int = 16, seed: int = 42) -> str:
    """The same tuples for DuckDB, one row per edge."""
    draws = "SELECT i, b, (i * 64 + b + {s}) % {p} AS x FROM range({m}) t(i), range({k}) s(b)".format(s=seed * SEED_STEP, p=PRIME, m=edge_factor << scale, k=scale)
    for a, c in ROUNDS:
        draws = f"SELECT i, b, (y * y + y) % {PRIME} AS x FROM (SELECT i, b, (x * {a} + {c}) % {PRIME} AS y FROM ({draws}))"
    bits = f"SELECT i, b, x % 100 AS r FROM ({draws})"
    one, two, three = SHARES
    return (
        f"SELECT CAST(sum(CASE WHEN r >= {two} THEN 1::BIGINT << ({scale} - 1 - b)::INTEGER ELSE 0 END) AS BIGINT) AS u, "
        f"CAST(sum(CASE WHEN (r >= {one} AND r < {two}) OR r >= {three} THEN 1::BIGINT << ({scale} - 1 - b)::INTEGER ELSE 0 END) AS BIGINT) AS v "
        f"FROM ({bits}) GROUP BY i"
    )


def edge_of(i: int, scale: int, seed: int) -> tuple[int, int]:
    """One tuple in plain Python: the reference for tests and for the data source."""
    u = v = 0
    for b in range(scale):
        x = (i * 64 + b + seed * SEED_STEP) % PRIME
        for a, c in ROUNDS:
            x = (x * a + c) % PRIME
            x = (x * x + x) % PRIME
        r = x % 100
        u = u << 1 | int(r >= SHARES[1])
        v = v << 1 | int(SHARES[0] <= r < SHARES[1] or r >= SHARES[2])
    return u, v


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class KroneckerSource(DataSource):
    """spark.read.format("kronecker").option("scale", ...): the convenient way; kronecker_edges is the fast one."""

    @classmethod
    def name(cls) -> str:
        return "kronecker"

    def schema(self) -> str:
        return "u bigint, v bigint"

    def reader(self, schema):
        return _Reader({k.lower(): v for k, v in self.options.items()})


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.scale, self.factor, self.seed = int(options.get("scale", 8)), int(options.get("edgefactor", 16)), int(options.get("seed", 42))
        self.parts = int(options.get("partitions", 8))

    def partitions(self):
        m = self.factor << self.scale
        step = -(-m // self.parts)
        return [_Range(i, min(i + step, m)) for i in range(0, m, step)]

    def read(self, partition):
        for i in range(partition.start, partition.stop):
            yield edge_of(i, self.scale, self.seed)
