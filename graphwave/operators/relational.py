"""Joins that graph derivations need beyond the plain ones: ranges, intervals, as-of, skewed hubs, and nearest neighbours."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(values: DataFrame, column: str, bounds: DataFrame, width: int) -> DataFrame:
    """Rows of values with the bounds row (lo, hi, ...) that lo <= value < hi holds for. Bounds are spread over cells of `width`, so it
    is an equality join on the cell with a test behind it, whatever their number."""
    cells = bounds.withColumn("__cell", F.explode(F.sequence(F.floor(F.col("lo") / width).cast("long"), F.floor((F.col("hi") - 1) / width).cast("long"))))
    keyed = values.withColumn("__cell", F.floor(F.col(column) / width).cast("long"))
    return keyed.join(cells, "__cell").where((F.col(column) >= F.col("lo")) & (F.col(column) < F.col("hi"))).drop("__cell")


def interval_pairs(events: DataFrame, key: str, time: str, id_column: str, seconds: int) -> DataFrame:
    """(a, b) of events of one key at most `seconds` apart, a before b. Each event meets its own time cell and the next, by equality on
    key and cell."""
    at = F.unix_micros(F.col(time).cast("timestamp")) / 1_000_000
    base = events.select(F.col(key).alias("k"), F.col(id_column).alias("id"), at.alias("t"), F.floor(at / seconds).cast("long").alias("cell"))
    left = base.select("k", F.col("id").alias("a"), F.col("t").alias("ta"), F.explode(F.array(F.col("cell"), F.col("cell") + 1)).alias("cell"))
    right = base.select("k", F.col("id").alias("b"), F.col("t").alias("tb"), "cell")
    near = left.join(right, ["k", "cell"]).where((F.col("tb") - F.col("ta") <= seconds) & ((F.col("tb") > F.col("ta")) | ((F.col("tb") == F.col("ta")) & (F.col("b") > F.col("a")))))
    return near.select("a", "b")


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str, order: str) -> DataFrame:
    """Rows of left with the latest earlier (or equal) value of right of the same key: one sort of both, no join. `order` settles equal
    times; right comes first."""
    tagged = left.select("*", F.lit(1).alias("__side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("__v"))
    other = right.select(key, time, order, F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = tagged.unionByName(other, allowMissingColumns=True)
    by = Window.partitionBy(key).orderBy(time, "__side", order).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("as_of", F.last("__v", ignorenulls=True).over(by)).where("__side = 1").drop("__side", "__v")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int) -> DataFrame:
    """An inner join on a skewed key: rows of the big side are dealt over `salts` parts of their key, and the small side is repeated for
    each part."""
    left = big.withColumn("__salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    right = small.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return left.join(right, [key, "__salt"]).drop("__salt")


def nearest(vectors: DataFrame, k: int, id_column: str = "vec_id", vector: str = "embedding", block: int = 4096) -> DataFrame:
    """(a, b): each vector's k nearest by cosine, ties by the smaller id. The vectors as queries go over all rows in blocks of bounded size;
    every task keeps k candidates for each query, and the best k of all tasks remain."""
    ids = vectors.select(id_column)
    n = ids.count()
    parts = max(1, -(-n // block))
    out = None
    for i in range(parts):
        queries = vectors if parts == 1 else vectors.where(F.pmod(F.xxhash64(id_column), F.lit(parts)) == i)
        rows = queries.select(id_column, vector).collect()
        keys = np.array([r[0] for r in rows], dtype=np.int64)
        matrix = np.array([r[1] for r in rows], dtype=np.float64)
        matrix /= np.maximum(np.linalg.norm(matrix, axis=1, keepdims=True), 1e-300)
        shared = vectors.sparkSession.sparkContext.broadcast((keys, matrix))

        def run(batches, shared=shared):
            own, q = shared.value
            for batch in batches:
                b = np.asarray(batch.column(0), dtype=np.int64)
                v = np.array(batch.column(1).to_pylist(), dtype=np.float64)
                v /= np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300)
                c = q @ v.T
                c[own[:, None] == b[None, :]] = -np.inf
                most = c.shape[1] - k - 1
                rows, cols = np.nonzero(c >= np.partition(c, most, axis=1)[:, [most]]) if most > 0 else np.nonzero(np.isfinite(c))
                order = np.lexsort((b[cols], -c[rows, cols], rows))  # only what ties with the last place is sorted
                rows, cols = rows[order], cols[order]
                nth = np.arange(len(rows)) - np.searchsorted(rows, rows)
                keep = (nth < k) & np.isfinite(c[rows, cols])
                yield pa.RecordBatch.from_arrays([pa.array(own[rows[keep]]), pa.array(b[cols[keep]]), pa.array(c[rows[keep], cols[keep]])], ["a", "b", "cosine"])

        found = vectors.select(id_column, vector).mapInArrow(run, "a long, b long, cosine double")
        out = found if out is None else out.unionByName(found)
    best = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("cosine"), "b"))
    return out.withColumn("r", best).where(F.col("r") <= k).select("a", "b", "cosine")
