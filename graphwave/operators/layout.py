"""Blocked graphs: ids, blocks, symmetric edges, adjacency lists, and how they are stored."""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.bits import block_of, block_size, slot_of
from ..plans.lineage import shared_dir
from ..sources.graphs import GRAPHS, Tuples


#: Edges that a partition has at least, if there is more than one.
PART_EDGES = 25_000


@dataclass
class GraphLayout:
    """edges(src, dst) distinct and without self-loops, dealt by src and written; p blocks of `size` ids."""

    edges: DataFrame
    tuples: DataFrame
    n: int
    p: int
    source: int = 0
    directed: bool = False
    name: str = ""
    m: int = 0
    extra: dict = field(default_factory=dict)

    @property
    def size(self) -> int:
        return block_size(self.n, self.p)

    @property
    def blocks(self) -> int:
        """Blocks that exist: fewer than p if the last ones would be empty."""
        return -(-self.n // self.size) if self.n else 0

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def release(self) -> None:
        """Frees what is kept in memory for the graph: edges, and what searches dealt from them."""
        for *_, held in self.extra.pop("program", []):
            held.unpersist()
        for key in [k for k in self.extra if k == "by_need" or isinstance(k, tuple)]:
            self.extra.pop(key).unpersist()
        self.edges.unpersist()

    def blocked(self) -> DataFrame:
        """(src, dst, src_block, src_slot, dst_block, dst_slot)."""
        b = self.size
        return self.edges.select("src", "dst", block_of("src", b).alias("src_block"), slot_of("src", b).alias("src_slot"), block_of("dst", b).alias("dst_block"), slot_of("dst", b).alias("dst_slot"))

    def frame(self) -> DataFrame:
        """(block, n_bits) of every block, from a range; its length is the number of blocks."""
        r = self.spark.range(self.blocks).select(F.col("id").alias("block"))
        return r.select("block", F.least(F.lit(self.size).cast("long"), F.lit(self.n).cast("long") - F.col("block") * self.size).alias("n_bits"))

    def vertices(self) -> DataFrame:
        return self.spark.range(self.n).select(F.col("id").alias("vid"), block_of("id", self.size).alias("block"), slot_of("id", self.size).alias("slot"))


def symmetrised(tuples: DataFrame, directed: bool = False) -> DataFrame:
    """Distinct (src, dst) without self-loops, both ways unless directed."""
    one = tuples.where("u <> v").select(F.col("u").alias("src"), F.col("v").alias("dst"))
    both = one if directed else one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return both.distinct()


def build(found: Tuples, p: int, directed: bool = False, name: str = "") -> GraphLayout:
    """Writes the edges to the shared folder and keeps them in memory dealt by src, so that no search moves them again: each level only
    moves its frontier. What an executor loses is read again from the written table."""
    spark = found.edges.sparkSession
    path = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}"
    symmetrised(found.edges, directed).write.parquet(path)
    written = spark.read.schema("src long, dst long").parquet(path)
    m = written.count()
    return GraphLayout(_dealt(written, m), found.edges, found.n, p, found.source, directed, name, m)


def _dealt(edges: DataFrame, m: int) -> DataFrame:
    """Edges by source, kept; a small graph in few partitions."""
    parts = max(1, min(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), -(-m // PART_EDGES)))
    return edges.repartition(parts, "src").persist(StorageLevel.MEMORY_AND_DISK)


def layout(spark: SparkSession, sf_dir: str, name: str, p: int | None = None) -> GraphLayout:
    g = GRAPHS[name]
    return build(g.build(spark, sf_dir), p or g.p, g.directed, name)


def adjacency_lists(g: GraphLayout, chunk: int = 4096) -> DataFrame:
    """(dst_block, src_block, src_slot, chunk, dst_slots): the columns of each sub-block; a hub's list is cut into chunks."""
    from pyspark.sql import Window

    by = Window.partitionBy("dst_block", "src").orderBy("dst_slot")
    rows = g.blocked().withColumn("chunk", F.floor((F.row_number().over(by) - 1) / chunk).cast("int"))
    return rows.groupBy("dst_block", "src_block", "src_slot", "chunk").agg(F.array_sort(F.collect_list("dst_slot")).alias("dst_slots"))


def save_layout(g: GraphLayout, path: str) -> None:
    g.blocked().repartition("dst_block").sortWithinPartitions("src_block", "src_slot").write.mode("overwrite").partitionBy("dst_block").parquet(f"{path}/edges")
    g.tuples.write.mode("overwrite").parquet(f"{path}/tuples")
    g.spark.createDataFrame([(g.n, g.p, g.source, g.directed, g.name)], "n long, p int, source long, directed boolean, name string").write.mode("overwrite").parquet(f"{path}/meta")


def load_layout(spark: SparkSession, path: str) -> GraphLayout:
    meta = spark.read.parquet(f"{path}/meta").first()
    edges = spark.read.parquet(f"{path}/edges").select("src", "dst")
    m = edges.count()
    return GraphLayout(_dealt(edges, m), spark.read.parquet(f"{path}/tuples"), meta["n"], meta["p"], meta["source"], meta["directed"], meta["name"], m)


def relabel(g: GraphLayout, factor: int, shift: int = 17) -> GraphLayout:
    """The same graph with ids permuted by (factor * v + shift) mod n; factor must be prime to n."""
    to = lambda c: F.pmod(F.col(c) * factor + shift, F.lit(g.n))
    found = Tuples(g.tuples.select(to("u").alias("u"), to("v").alias("v")), g.n, (g.source * factor + shift) % g.n)
    return build(found, g.p, g.directed, f"{g.name}_relabelled")


def fingerprint(g: GraphLayout) -> tuple[int, int, int, int]:
    """What has to stay the same for a directory to be reused: edges (count and hash sum), n and p."""
    r = g.edges.agg(F.count("*").alias("m"), F.sum(F.xxhash64("src", "dst").cast("decimal(38,0)")).alias("h")).first()
    return r["m"], int(r["h"] or 0), g.n, g.p
