"""Encoders as column functions, and the ledgers of what searches send: all-gather, all-to-all, pull, rendezvous, coalescing, grid."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codecs import CODECS
from ..functions import sizes
from .directory import all_pairs
from .layout import GraphLayout


def encoder(codec: str):
    encode, _ = CODECS[codec]

    @F.pandas_udf("binary")
    def run(slots: pd.Series, n_bits: pd.Series) -> pd.Series:
        return pd.Series([encode(np.asarray(s, dtype=np.int64), int(n)) for s, n in zip(slots, n_bits, strict=True)])

    return run


def decoder(codec: str):
    _, decode = CODECS[codec]

    @F.pandas_udf("array<long>")
    def run(payload: pd.Series, n_bits: pd.Series) -> pd.Series:
        return pd.Series([decode(p, int(n)).astype(np.int64) for p, n in zip(payload, n_bits, strict=True)])

    return run


# ---------------------------------------------------------------------------------------------------------------------
# ledgers from a finished tree: what is sent follows from level sets, blocks and directory alone


def ledger(g: GraphLayout, tree: DataFrame, codec: str, needs: DataFrame | None = None, skip_empty: bool = False) -> DataFrame:
    """(level, owner_block, needer_block, n_set, raw_bytes, bytes) of a whole search, by the set lane. Every pair of different blocks has a
    message at every level, unless skip_empty."""
    b = g.size
    members = tree.select("level", "vid", F.floor(F.col("vid") / b).cast("long").alias("owner_block"), F.pmod(F.col("vid"), F.lit(b)).cast("long").alias("slot"))
    levels = tree.select("level").distinct()
    if needs is None:
        keys = ["level", "owner_block"]
        frame = levels.join(F.broadcast(g.frame().withColumnRenamed("block", "owner_block")))  # one row per block
        members = members.join(g.frame().withColumnRenamed("block", "owner_block"), "owner_block").select(*keys, "slot", "n_bits")
        out = sizes.sized(members, frame.select(*keys, "n_bits"), keys, codec)
        out = out.withColumn("needer_block", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(g.blocks - 1).cast("long")))).where("needer_block <> owner_block")
    else:
        keys = ["level", "owner_block", "needer_block"]
        frame = levels.join(F.broadcast(all_pairs(g)))  # one row per pair of blocks
        members = members.join(needs.where("needer_block <> owner_block"), ["owner_block", "slot"]).join(g.frame().withColumnRenamed("block", "owner_block"), "owner_block").select(*keys, "slot", "n_bits")
        out = sizes.sized(members, frame.select(*keys, "n_bits"), keys, codec)
    if skip_empty:
        out = out.where("n_set > 0")
    return out.select("level", "owner_block", "needer_block", "n_set", sizes.bitmap_bytes(F.col("n_bits")).alias("raw_bytes"), F.col("bytes").cast("long").alias("bytes"))


def pull_ledger(g: GraphLayout, tree: DataFrame, needs: DataFrame, codec: str = "wah", request_bytes: int = 8) -> DataFrame:
    """(level, owner_block, needer_block, direction, n_messages, bytes) of the request and reply protocol: a needer asks each owner whose
    vector in its directory has members, the owner masks its frontier by its copy of the vector and replies."""
    asked = needs.where("needer_block <> owner_block").select("owner_block", "needer_block").distinct()
    replies = ledger(g, tree, codec, needs).join(asked, ["owner_block", "needer_block"])
    one = F.lit(1).cast("long").alias("n_messages")
    out = replies.select("level", "owner_block", "needer_block", F.lit("reply").alias("direction"), one, "bytes")
    return out.unionByName(replies.select("level", "owner_block", "needer_block", F.lit("request").alias("direction"), one, F.lit(request_bytes).cast("long").alias("bytes")))


def rendezvous_ledger(book: DataFrame, alpha: float = 1.0e-6, beta: float = 2.5e-10) -> DataFrame:
    """(level, owner_block, needer_block, n_messages, bytes, seconds) of exchanging message by message: each costs its latency too."""
    out = book.groupBy("level", "owner_block", "needer_block").agg(F.count("*").alias("n_messages"), F.sum("bytes").alias("bytes"))
    return out.withColumn("seconds", F.round(F.col("n_messages") * alpha + F.col("bytes") * beta, 12))


def coalesced_ledger(book: DataFrame, hosts: int) -> DataFrame:
    """(level, owner_host, needer_host, n_messages, bytes): messages of blocks on one host to blocks on another travel together, with
    block modulo hosts as the host."""
    host = lambda c: F.pmod(F.col(c), F.lit(hosts)).cast("long")
    rows = book.select("level", host("owner_block").alias("owner_host"), host("needer_block").alias("needer_host"), "bytes").where("owner_host <> needer_host")
    return rows.groupBy("level", "owner_host", "needer_host").agg(F.lit(1).cast("long").alias("n_messages"), F.sum("bytes").alias("bytes"))


def grid_ledger(g: GraphLayout, tree: DataFrame, rows: int, cols: int) -> DataFrame:
    """(level, phase, from_block, to_block, n_set, bytes) of a two-dimensional partition: the frontier expands along grid columns, and
    candidates fold along grid rows. Ids are 8 bytes."""
    br, bc = -(-g.n // rows), -(-g.n // cols)
    cell = lambda v: (F.floor(F.col(v) / br).cast("long"), F.floor(F.col(v) / bc).cast("long"))
    # a vertex is owned by the cell of its row range and column range
    r, c = cell("vid")
    own = tree.select("level", "vid", r.alias("row"), c.alias("col"))
    expand = own.withColumn("to", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(rows - 1).cast("long")))).where(F.col("to") != F.col("row"))
    expand = expand.groupBy("level", (F.col("row") * cols + F.col("col")).alias("from_block"), (F.col("to") * cols + F.col("col")).alias("to_block")).agg(F.count("*").alias("n_set"))
    dr, dc = cell("dst")
    reached = g.edges.join(tree.select("level", F.col("vid").alias("src")), "src").select("level", "dst", dr.alias("row"), dc.alias("home"), F.floor(F.col("src") / bc).cast("long").alias("col")).distinct()
    fold = reached.where("col <> home").groupBy("level", (F.col("row") * cols + F.col("col")).alias("from_block"), (F.col("row") * cols + F.col("home")).alias("to_block")).agg(F.count("*").alias("n_set"))
    both = expand.withColumn("phase", F.lit("expand")).unionByName(fold.withColumn("phase", F.lit("fold")))
    return both.select("level", "phase", "from_block", "to_block", "n_set", (F.col("n_set") * 8).alias("bytes"))
