"""Sparse products of the adjacency matrix with vectors, over several semirings."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .directory import build_needs, sieve
from .layout import GraphLayout

#: How the values that meet at a row are combined.
COMBINE = {"plus_times": F.sum, "max_plus": F.max, "min_plus": F.min, "or_and": F.max}


def expand(g: GraphLayout, frontier: DataFrame) -> DataFrame:
    """(dst, src) of every edge that leaves the frontier (vid)."""
    return g.edges.join(frontier.select(F.col("vid").alias("src")), "src").select("dst", "src")


def combine(candidates: DataFrame, how: str = "max") -> DataFrame:
    """(vid, parent): one value for each candidate vertex; partial aggregates come before the exchange."""
    agg = {"max": F.max("src"), "min": F.min("src"), "count": F.count("*")}[how]
    return candidates.groupBy(F.col("dst").alias("vid")).agg(agg.alias("parent"))


def _value(semiring: str):
    """What an edge makes of a value: paths get longer by one."""
    return F.col("val") + 1 if semiring in ("max_plus", "min_plus") else F.col("val")


def dealt_by_need(g: GraphLayout) -> DataFrame:
    """(src, needer_block, dst): the edges dealt by source and needer, as sieved values arrive; made once."""
    held = g.extra.get("by_need")
    if held is None:
        rows = g.edges.select("src", F.floor(F.col("dst") / g.size).cast("long").alias("needer_block"), "dst")
        parts = max(1, g.edges.rdd.getNumPartitions())
        held = g.extra["by_need"] = rows.repartition(parts, "src", "needer_block").persist(StorageLevel.MEMORY_AND_DISK)
    return held


def spmv(g: GraphLayout, x: DataFrame, semiring: str = "plus_times", sieved: bool = False, needs: DataFrame | None = None) -> DataFrame:
    """(vid, y) for x(vid, val): y at a row combines val of its neighbours (plus 1 for the semirings of path lengths). sieved: x is first
    cut to what the directory says is needed, which changes nothing but what is sent; the edges stay where they are."""
    if sieved:
        edges = dealt_by_need(g)
        kept = sieve(g, x.select("vid", "val"), build_needs(g) if needs is None else needs).select(F.col("vid").alias("src"), "val", "needer_block")
        joined = edges.join(kept.repartition(edges.rdd.getNumPartitions(), "src", "needer_block"), ["src", "needer_block"])
    else:
        joined = g.edges.join(x.select(F.col("vid").alias("src"), "val"), "src")
    return joined.groupBy(F.col("dst").alias("vid")).agg(COMBINE[semiring](_value(semiring)).alias("y"))


def spmv_many(g: GraphLayout, vectors: DataFrame, semiring: str = "plus_times") -> DataFrame:
    """(vid, y): the products with many vectors x(vec_id, vid, val), combined over the vectors as within one; all vectors meet the matrix
    in one pass."""
    joined = g.edges.join(vectors.select("vec_id", F.col("vid").alias("src"), "val"), "src")
    each = joined.groupBy("vec_id", F.col("dst").alias("vid")).agg(COMBINE[semiring](_value(semiring)).alias("y"))
    return each.groupBy("vid").agg(COMBINE[semiring]("y").alias("y"))
