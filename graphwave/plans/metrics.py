"""Measures over trees, tuples and profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.layout import GraphLayout


def level_sizes(tree: DataFrame) -> DataFrame:
    """(level, n, reached): frontier sizes and how many are reached so far."""
    n = tree.groupBy("level").agg(F.count("*").alias("n"))
    return n.withColumn("reached", F.sum("n").over(Window.orderBy("level").rowsBetween(Window.unboundedPreceding, 0)))  # one row per level


def encoding_sizes(counts: DataFrame, n_bits: int | None) -> DataFrame:
    """(level, n, bitmap_bytes, sparse_bytes), and a row with a null level for the totals. counts: (level, n); n_bits None: their sum."""
    bits = F.lit(n_bits).cast("long") if n_bits is not None else F.lit(counts.agg(F.sum("n")).first()[0]).cast("long")
    rows = counts.select("level", "n", F.ceil(bits / 8).cast("long").alias("bitmap_bytes"), (F.col("n") * 8).alias("sparse_bytes"))
    return rows.rollup("level").agg(F.sum("n").alias("n"), F.sum("bitmap_bytes").alias("bitmap_bytes"), F.sum("sparse_bytes").alias("sparse_bytes"))


def breakeven(counts: DataFrame, n_bits: int) -> DataFrame:
    """(depth, bitmap_bits, sparse_bits, winner): all levels as bitmaps against 64-bit ids."""
    one = counts.agg(F.count("*").alias("depth"), F.sum("n").alias("reached"))
    bitmap, sparse = F.col("depth") * F.lit(n_bits).cast("long"), F.col("reached") * 64
    return one.select("depth", bitmap.alias("bitmap_bits"), sparse.alias("sparse_bits"), F.when(bitmap <= sparse, "bitmap").otherwise("sparse").alias("winner"))


def teps_edges(tuples: DataFrame, tree: DataFrame) -> DataFrame:
    """(m_tuples, m_selfloops, m_distinct) inside the reached component: input tuples with their duplicates and self-loops."""
    inside = tuples.join(tree.select(F.col("vid").alias("u")), "u", "left_semi")
    pair = F.struct(F.least("u", "v"), F.greatest("u", "v"))
    return inside.agg(F.count("*").alias("m_tuples"), F.sum((F.col("u") == F.col("v")).cast("long")).alias("m_selfloops"), F.count_distinct(F.when(F.col("u") != F.col("v"), pair)).alias("m_distinct"))


def graph_stats(g: GraphLayout, tree: DataFrame) -> DataFrame:
    """(n, m, touched, mean_degree, max_degree, depth, reached)."""
    degree = g.edges.groupBy("src").agg(F.count("*").alias("d"))
    e = degree.agg(F.count("*").alias("touched"), F.sum("d").alias("directed"), F.max("d").alias("max_degree"))
    t = tree.agg(F.max("level").alias("depth"), F.count("*").alias("reached"))
    half = 1 if g.directed else 2
    out = e.join(F.broadcast(t))  # one row each
    m = F.floor(F.coalesce("directed", F.lit(0)) / half).cast("long")
    return out.select(F.lit(g.n).cast("long").alias("n"), m.alias("m"), "touched", F.round(m / F.lit(g.n), 6).alias("mean_degree"), F.coalesce("max_degree", F.lit(0)).alias("max_degree"), "depth", "reached")


def degree_histogram(g: GraphLayout) -> DataFrame:
    d = g.edges.groupBy("src").agg(F.count("*").alias("degree"))
    return d.groupBy("degree").agg(F.count("*").alias("vertices"))


def imbalance(g: GraphLayout) -> DataFrame:
    """(blocks, edges, max_edges, ratio): edges of the heaviest block against the mean."""
    by = g.frame().join(g.blocked().groupBy(F.col("dst_block").alias("block")).agg(F.count("*").alias("e")), "block", "left").select(F.coalesce("e", F.lit(0)).alias("e"))
    return by.agg(F.count("*").alias("blocks"), F.sum("e").alias("edges"), F.max("e").alias("max_edges"), F.round(F.max("e") / F.avg("e"), 6).alias("ratio"))


def phase_shares(profile: DataFrame) -> DataFrame:
    """(run_id, method, phase, seconds, share)."""
    s = profile.groupBy("run_id", "method", "phase").agg(F.sum("seconds").alias("seconds"))
    return s.withColumn("share", F.round(F.col("seconds") / F.sum("seconds").over(Window.partitionBy("run_id", "method")), 6))


def compare_runs(totals: DataFrame, base: str) -> DataFrame:
    """(method, seconds, communication, speedup, reduction) against a base method; totals: (method, seconds, communication)."""
    b = totals.where(F.col("method") == base).select(F.col("seconds").alias("bs"), F.col("communication").alias("bc"))
    out = totals.join(F.broadcast(b))  # the base is one row
    return out.select("method", "seconds", "communication", F.round(F.col("bs") / F.col("seconds"), 6).alias("speedup"), F.round(1 - F.col("communication") / F.col("bc"), 6).alias("reduction"))


def relative_performance(totals: DataFrame, base: str) -> DataFrame:
    """(method, seconds, relative): the base method's seconds over this one's, in per cent."""
    b = totals.where(F.col("method") == base).select(F.col("seconds").alias("bs"))
    return totals.join(F.broadcast(b)).select("method", "seconds", F.round(F.col("bs") * 100 / F.col("seconds"), 6).alias("relative"))


def harmonic_rate(rates: DataFrame) -> DataFrame:
    return rates.agg((F.count("*") / F.sum(1 / F.col("rate"))).alias("rate"))
