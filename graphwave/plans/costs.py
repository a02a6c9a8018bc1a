"""The cost model: message and collective times, volumes, compression ratios, memory, and what a directory costs and saves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sizes
from ..operators.layout import GraphLayout


def ratio(a, b, digits: int = 6):
    return F.round(a / b, digits)


def message_time(nbytes, alpha: float, beta: float):
    """Seconds of one message of n bytes: latency and transfer. alpha=0 leaves bandwidth only."""
    return F.lit(alpha) + nbytes * F.lit(beta)


def collective_time(kind: str, p, nbytes, alpha: float, beta: float):
    """Seconds of an all-gather of nbytes in total among p: ring or recursive doubling."""
    rounds = p - 1 if kind == "ring" else F.log2(p)
    return rounds * F.lit(alpha) + (p - 1) / p * nbytes * F.lit(beta)


def collective_table(spark, ps=(2, 4, 8, 64, 512), nbytes=(8 << 20, 1 << 30), alpha: float = 2.0e-6, beta: float = 2.5e-10) -> DataFrame:
    base = spark.createDataFrame([(p, n) for p in ps for n in nbytes], "p long, nbytes long")
    one = lambda kind: base.select(F.lit(kind).alias("kind"), "p", "nbytes", F.round(collective_time(kind, F.col("p"), F.col("nbytes"), alpha, beta), 9).alias("seconds"))
    return one("ring").unionByName(one("doubling"))


def message_table(spark, nbytes=(0, 8, 1024, 1 << 20, 1 << 30), alpha: float = 2.0e-6, beta: float = 2.5e-10) -> DataFrame:
    base = spark.createDataFrame([(n,) for n in nbytes], "nbytes long")
    return base.select("nbytes", F.round(message_time(F.col("nbytes"), alpha, beta), 12).alias("seconds"), F.round(message_time(F.col("nbytes"), 0.0, beta), 12).alias("bandwidth_seconds"))


def block_volume(book: DataFrame) -> DataFrame:
    """(block, sent, received, total) bytes over a whole search."""
    sent = book.groupBy(F.col("owner_block").alias("block")).agg(F.sum("bytes").alias("sent"))
    got = book.groupBy(F.col("needer_block").alias("block")).agg(F.sum("bytes").alias("received"))
    both = sent.join(got, "block", "full_outer")
    s, r = F.coalesce("sent", F.lit(0)), F.coalesce("received", F.lit(0))
    return both.select("block", s.alias("sent"), r.alias("received"), (s + r).alias("total"))


def algorithm_volume(book: DataFrame) -> DataFrame:
    """(volume, max_received, all_bytes, messages): the largest block's volume, and the largest received."""
    return block_volume(book).agg(F.max("total").alias("volume"), F.max("received").alias("max_received"), F.sum("sent").alias("all_bytes"))


def compression_ratio(book: DataFrame) -> DataFrame:
    """(level, raw_bytes, bytes, ratio): how often the encoded bytes go into the plain bitmap's."""
    out = book.groupBy("level").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes").alias("bytes"))
    return out.select("level", "raw_bytes", "bytes", ratio(F.col("raw_bytes"), F.col("bytes")).alias("ratio"))


def compression_factor(book: DataFrame) -> DataFrame:
    """(factor, levels): the mean over levels of encoded to plain bytes."""
    by = book.groupBy("level").agg((F.sum("bytes") / F.sum("raw_bytes")).alias("share"))
    return by.agg(F.round(F.avg("share"), 6).alias("factor"), F.count("*").alias("levels"))


def message_counts(book: DataFrame) -> DataFrame:
    """(level, messages, with_members)."""
    return book.groupBy("level").agg(F.count("*").alias("messages"), F.sum((F.col("n_set") > 0).cast("long")).alias("with_members"))


def block_memory(g: GraphLayout, method: str, needs: DataFrame | None = None) -> DataFrame:
    """(block, frontier, candidates, visited, directory, total) bytes a worker holds: a bitmap over all ids for the frontier it multiplies
    (with a directory, what it needs of each owner), 8 bytes for each of its own candidates, a bitmap of its visited ids, and the
    directory's vectors in both views."""
    f = g.frame()
    whole = F.lit(-(-g.n // 8)).cast("long")
    own = sizes.bitmap_bytes(F.col("n_bits"))
    base = f.select("block", whole.alias("frontier"), (F.col("n_bits") * 8).alias("candidates"), own.alias("visited"), (F.lit(0) if not method.endswith("sieved") else whole + own * F.lit(g.blocks)).cast("long").alias("directory"))
    return base.withColumn("total", F.expr("frontier + candidates + visited + directory"))


def directory_cost(g: GraphLayout, needs: DataFrame) -> DataFrame:
    """(entries, vectors, setup_messages, setup_bytes): the directory's size and what it takes to send each vector to its owner once."""
    away = needs.where("needer_block <> owner_block")
    setup = F.sum(F.lit(g.blocks - 1) * sizes.bitmap_bytes(F.col("n_bits")))
    cost = g.frame().agg(setup.cast("long").alias("setup_bytes"), (F.count("*") * (g.blocks - 1)).alias("setup_messages"))
    counts = away.agg(F.count("*").alias("entries"), F.countDistinct("needer_block", "owner_block").alias("vectors"))
    return counts.join(F.broadcast(cost)).select("entries", "vectors", "setup_messages", "setup_bytes")  # one row each


def amortisation(plain: DataFrame, sieved: DataFrame, cost: DataFrame) -> DataFrame:
    """(plain_bytes, sieved_bytes, setup_bytes, searches): after how many searches the directory's set-up is repaid; null if never."""
    a = plain.agg(F.sum("bytes").alias("plain_bytes"))
    b = sieved.agg(F.sum("bytes").alias("sieved_bytes"))
    out = a.join(F.broadcast(b)).join(F.broadcast(cost.select("setup_bytes")))  # one row each
    saved = F.col("plain_bytes") - F.col("sieved_bytes")
    return out.select("plain_bytes", "sieved_bytes", "setup_bytes", F.when(saved > 0, F.ceil(F.col("setup_bytes") / saved)).alias("searches"))


def choose_encoding(n_bits, n_set, runs=None):
    """Name of the smallest expected encoding of a message: nothing for an empty one, ids when very sparse, gaps, word-aligned runs, or
    the plain bitmap. runs: how many runs of ones, if known; members at worst."""
    runs = n_set if runs is None else runs
    bitmap = F.ceil(n_bits / 8)
    # a gap takes about one byte for each seven bits of the mean distance
    gap = n_set * (F.lit(1) + F.floor(F.log2(F.greatest(n_bits / F.greatest(n_set, F.lit(1)), F.lit(1.0))) / 7))
    wah = F.least(runs * 2 + 1, F.ceil(n_bits / 31)) * 4
    best = F.least(bitmap, gap, wah, n_set * 8)
    return F.when(n_set == 0, "empty").when(n_set * 8 == best, "sparse").when(gap == best, "varint").when(wah == best, "wah").otherwise("bitmap")
