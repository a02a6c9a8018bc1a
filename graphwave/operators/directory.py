"""Needs-directories: which of its slots an owner block must send to which needer block.

`needs(needer_block, owner_block, slot)` has a row for each column of a sub-block that isn't empty. It is made once per graph and
serves every search and product over the same edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import sizes
from ..plans.lineage import cut, gated
from .layout import GraphLayout, fingerprint


def build_needs(g: GraphLayout) -> DataFrame:
    e = g.blocked()
    return e.select(F.col("dst_block").alias("needer_block"), F.col("src_block").alias("owner_block"), F.col("src_slot").alias("slot")).distinct()


def needs_of(needs: DataFrame, block: int) -> DataFrame:
    """The row view: what a block needs of the others."""
    return needs.where(F.col("needer_block") == block)


def needed_from(needs: DataFrame, block: int) -> DataFrame:
    """The column view: what the others need of a block."""
    return needs.where(F.col("owner_block") == block)


def pack_needs(g: GraphLayout, needs: DataFrame, codec: str = "bitmap") -> DataFrame:
    """(needer_block, owner_block, n_set, bytes) of the directory's vectors that have members."""
    frame = needs.select("needer_block", "owner_block").distinct().join(g.frame().withColumnRenamed("block", "owner_block"), "owner_block")
    members = needs.join(g.frame().withColumnRenamed("block", "owner_block"), "owner_block")
    return sizes.sized(members, frame, ["needer_block", "owner_block"], codec).select("needer_block", "owner_block", "n_set", "bytes")


def native_bitmaps(needs: DataFrame) -> DataFrame:
    """(needer_block, owner_block, bucket, bits, n_set) by Spark's own bitmap aggregates; slots are passed as slot + 1, since these
    functions put 0 in a bucket of its own."""
    at = F.col("slot") + 1
    rows = needs.withColumns({"bucket": F.bitmap_bucket_number(at), "bit": F.bitmap_bit_position(at)})
    return rows.groupBy("needer_block", "owner_block", "bucket").agg(F.bitmap_construct_agg("bit").alias("bits")).withColumn("n_set", F.bitmap_count("bits"))


def directory_setup_ledger(g: GraphLayout, needs: DataFrame) -> DataFrame:
    """(needer_block, owner_block, bytes): every vector goes from needer to owner once, as a bitmap; the diagonal stays at home."""
    pairs = all_pairs(g)
    return pairs.select("needer_block", "owner_block", sizes.bitmap_bytes(F.col("n_bits")).alias("bytes"))


def all_pairs(g: GraphLayout) -> DataFrame:
    """(owner_block, needer_block, n_bits): p x (p - 1) rows from ranges over blocks."""
    owners = g.frame().withColumnRenamed("block", "owner_block")
    to = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(g.blocks - 1).cast("long")))
    return owners.withColumn("needer_block", to).where("needer_block <> owner_block")


def sieve(g: GraphLayout, frontier: DataFrame, needs: DataFrame) -> DataFrame:
    """(needer_block, owner_block, slot) of the frontier's deliveries, own block included. frontier has vid."""
    b = g.size
    own = frontier.withColumns({"owner_block": F.floor(F.col("vid") / b).cast("long"), "slot": F.pmod(F.col("vid"), F.lit(b)).cast("long")})
    return own.join(needs, ["owner_block", "slot"])


def receiver_counts(g: GraphLayout, needs: DataFrame) -> DataFrame:
    """(vid, receivers) of every vertex that another block needs."""
    away = needs.where("needer_block <> owner_block")
    return away.groupBy("owner_block", "slot").agg(F.count("*").alias("receivers")).select((F.col("owner_block") * g.size + F.col("slot")).alias("vid"), "receivers")


def receiver_bounds(g: GraphLayout, needs: DataFrame) -> DataFrame:
    """(vid, receivers, bound, ok): at most the smaller of the vertex's degree and the number of other blocks."""
    degree = g.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("degree"))
    bound = F.least(F.col("degree"), F.lit(g.blocks - 1).cast("long"))
    out = receiver_counts(g, needs).join(degree, "vid")
    return out.select("vid", "receivers", bound.alias("bound"), (F.col("receivers") <= bound).alias("ok"))


def sieve_ratio(g: GraphLayout, tree: DataFrame, needs: DataFrame) -> DataFrame:
    """(level, plain, sieved, ratio): deliveries to other blocks without and with the directory."""
    level = tree.groupBy("level").agg(F.count("*").alias("n"))
    sieved = sieve(g, tree, needs.where("needer_block <> owner_block")).groupBy("level").agg(F.count("*").alias("s"))
    plain = F.col("n") * (g.blocks - 1)
    out = level.join(sieved, "level", "left").withColumn("s", F.coalesce("s", F.lit(0)))
    return out.select("level", plain.alias("plain"), F.col("s").alias("sieved"), F.round(F.col("s") / F.greatest(plain, F.lit(1)), 6).alias("ratio"))


def directory_profile(needs: DataFrame, blocks: int) -> DataFrame:
    """(needer_block, o0, o1, ...): members of each vector as a blocks x blocks table."""
    wide = needs.groupBy("needer_block").pivot("owner_block", list(range(blocks))).count()
    return wide.select("needer_block", *[F.coalesce(F.col(f"`{i}`"), F.lit(0)).cast("long").alias(f"o{i}") for i in range(blocks)])


def needs_counts(g: GraphLayout, edges: DataFrame) -> DataFrame:
    """(needer_block, owner_block, slot, edges): the directory with how many edges stand behind an entry, for upkeep."""
    b = g.size
    key = [F.floor(F.col("dst") / b).cast("long").alias("needer_block"), F.floor(F.col("src") / b).cast("long").alias("owner_block"), F.pmod(F.col("src"), F.lit(b)).cast("long").alias("slot")]
    return edges.groupBy(*key).agg(F.count("*").alias("edges"))


def apply_edge_delta(g: GraphLayout, counts: DataFrame, added: DataFrame | None, removed: DataFrame | None) -> DataFrame:
    """The directory after edges came and went. The entries stay where they are: they meet the changes, which are counted first and
    broadcast if they are few. An entry without edges is gone."""
    parts = [needs_counts(g, added)] if added is not None else []
    if removed is not None:
        parts.append(needs_counts(g, removed).withColumn("edges", -F.col("edges")))
    if not parts:
        return counts
    changes = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    key = ["needer_block", "owner_block", "slot"]
    changes = cut(changes.groupBy(*key).agg(F.sum("edges").alias("change")))
    n = changes.count()
    kept = counts.join(gated(changes, n), key, "left").select(*key, (F.col("edges") + F.coalesce("change", F.lit(0))).alias("edges"))
    met = counts.join(gated(changes.select(*key), n), key, "left_semi").select(*key)
    fresh = changes.join(gated(met, n), key, "left_anti").select(*key, F.col("change").alias("edges"))
    return kept.unionByName(fresh).where("edges > 0")


class Directory:
    """Needs of a graph, written and dealt by owner, with the fingerprint it was made for."""

    def __init__(self, g: GraphLayout):
        self.graph, self.stamp = g, fingerprint(g)
        self.needs = cut(build_needs(g).repartition("owner_block"))

    def assert_static(self) -> None:
        if fingerprint(self.graph) != self.stamp:
            raise ValueError("the graph or its blocks changed since the directory was made")
