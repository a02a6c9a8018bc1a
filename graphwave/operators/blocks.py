"""Searches by messages as programs of blocks: one task holds a block's edges, directory and visited bits, and a level is one exchange.

At each level a block restores the frontiers that it was sent, takes its columns to candidates, drops what it has visited, sieves what is
new by its directory, packs it and sends it on. The edges and the directory are dealt by block once and stay where they are; only packed
messages and the visited bits (a bit an id) pass through the exchange. Each level's result is written to the shared folder, so a lost
executor costs at most a level's work; when the search ends, what the levels wrote is deleted, and tree and ledger remain.

A block's edges have to fit into a task; p is chosen by that. They are handed over in parts of bounded size.
"""

from __future__ import annotations

import time
import uuid
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions import sizes
from ..functions.codecs import CODECS, decode_many, encode_many
from ..plans.lineage import delete, shared_dir
from .layout import GraphLayout

#: Edges that one part of a block holds about.
PART = 4_000_000
STATIC = "block long, kind string, a binary, b binary, c binary"
ROW = "to_block long, kind string, owner long, n_bits long, n_set long, payload binary, slots array<int>, parents array<long>"
_NAMES = ["to_block", "kind", "owner", "n_bits", "n_set", "payload", "slots", "parents"]
PHASES = ("traversing", "reducing", "compression_sieve")



def _csr(keys: np.ndarray, values: np.ndarray) -> tuple[bytes, bytes, bytes]:
    """Distinct keys, where their values begin and end, and the values, keys and values in order."""
    order = np.lexsort((values, keys))
    keys, values = keys[order], values[order]
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[first].tobytes(), np.append(first, len(keys)).astype(np.int64).tobytes(), values.astype(np.int32).tobytes()


def _packer(kind: str, key: str, value: str):
    def run(table: pa.Table) -> pa.Table:
        block = table.column("block")[0].as_py()
        a, b, c = _csr(table.column(key).to_numpy().astype(np.int64), table.column(value).to_numpy())
        return pa.table({"block": pa.array([block], pa.int64()), "kind": [kind], "a": pa.array([a], pa.binary()), "b": pa.array([b], pa.binary()), "c": pa.array([c], pa.binary())})

    return run


def tasks_of(g: GraphLayout) -> int:
    return max(1, min(int(g.spark.conf.get("spark.sql.shuffle.partitions", "200")), g.blocks))


def program(g: GraphLayout, needs: DataFrame | None, edges: bool = True) -> DataFrame:
    """(block, kind, a, b, c): the columns of each block's rows, and its directory as an owner; dealt by block, sorted, kept in memory
    over the written edges. Made once per graph and directory."""
    held = g.extra.setdefault("program", [])
    for known, with_edges, made in held:
        if known is needs and with_edges == edges:
            return made
    parts = []
    if edges:
        rows = g.edges.select(F.floor(F.col("dst") / g.size).cast("long").alias("block"), "src", F.pmod(F.col("dst"), F.lit(g.size)).cast("int").alias("slot"))
        most = rows.groupBy("block").count().agg(F.max("count")).first()[0] or 0
        part = F.pmod(F.xxhash64("src"), F.lit(max(1, -(-most // PART)))).alias("part")
        parts.append(rows.withColumn("part", part).groupBy("block", "part").applyInArrow(_packer("edges", "src", "slot"), STATIC))
    if needs is not None:
        rows = needs.select(F.col("owner_block").alias("block"), "needer_block", F.col("slot").cast("int").alias("slot"))
        parts.append(rows.groupBy("block").applyInArrow(_packer("needs", "needer_block", "slot"), STATIC))
    made = _union(parts).repartition(tasks_of(g), "block").sortWithinPartitions("block").persist(StorageLevel.MEMORY_AND_DISK)
    made.count()
    held.append((needs, edges, made))
    return made


def _asked(g: GraphLayout, needs: DataFrame) -> DataFrame:
    """The row view of the directory: whom each block has to ask."""
    for known, turned in g.extra.setdefault("asked", []):
        if known is needs:
            return turned
    turned = needs.select(F.col("needer_block").alias("owner_block"), F.col("owner_block").alias("needer_block"), F.lit(0).alias("slot")).distinct()
    g.extra["asked"].append((needs, turned))
    return turned


# ---------------------------------------------------------------------------------------------------------------------
# what a block does


@dataclass(frozen=True)
class Plan:
    """What the tasks need to know. asks: blocks request frontiers instead of being sent them."""

    size: int
    n: int
    codec: str
    sieved: bool
    combine: str
    asks: bool = False

    def bits(self, block: int) -> int:
        return min(self.size, self.n - block * self.size)


class _Static:
    def __init__(self, table: pa.Table):
        self.edges, self.needs = [], []
        for kind, a, b, c in zip(*(table.column(x).to_pylist() for x in ("kind", "a", "b", "c")), strict=True):
            arrays = np.frombuffer(a, np.int64), np.frombuffer(b, np.int64), np.frombuffer(c, np.int32)
            (self.edges if kind == "edges" else self.needs).append(arrays)


def _candidates(static: _Static, arrived: np.ndarray, bits: int, how: str) -> np.ndarray:
    """For every slot of the block what its arrived neighbours combine to; -1 without any."""
    best = np.full(bits, -1 if how == "max" else np.iinfo(np.int64).max, np.int64) if how != "count" else np.zeros(bits, np.int64)
    for src, ends, slots in static.edges:
        at = np.searchsorted(src, arrived)
        at[at == len(src)] = 0
        hit = src[at] == arrived
        at, ids = at[hit], arrived[hit]
        n = ends[at + 1] - ends[at]
        where = np.repeat(ends[at] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        target = slots[where]
        if how == "count":
            best += np.bincount(target, minlength=bits)
        else:
            (np.maximum if how == "max" else np.minimum).at(best, target, np.repeat(ids, n))
    if how == "min":
        best[best == np.iinfo(np.int64).max] = -1
    elif how == "count":
        best[best == 0] = -1
    return best


def _sieved(static: _Static, mask: np.ndarray):
    """(needers, slots, ends): what each needer can use."""
    for needers, ends, slots in static.needs:
        hit = mask[slots]
        yield needers, slots[hit].astype(np.int64), np.concatenate(([0], np.cumsum(hit)))[ends]


class _Out:
    def __init__(self):
        self.rows = []

    def add(self, to, kind, owner=None, n_bits=None, n_set=None, payload=None, slots=None, parents=None):
        self.rows.append((to, kind, owner, n_bits, n_set, payload, slots, parents))

    def table(self) -> pa.Table:
        types = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.int32()), pa.list_(pa.int64())]
        cols = list(zip(*self.rows, strict=True)) if self.rows else [[]] * 8
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], _NAMES)


def expander(plan: Plan):
    """The level step of a block: (key, static rows, inbox) to outgoing rows."""

    def run(key, static_rows: pa.Table, inbox: pa.Table) -> pa.Table:
        block = key[0].as_py()
        bits, out, spent = plan.bits(block), _Out(), dict.fromkeys(PHASES, 0.0)
        clock = time.perf_counter()

        def lap(phase):
            nonlocal clock
            now = time.perf_counter()
            spent[phase] += now - clock
            clock = now

        static = _Static(static_rows)
        visited, mail, seeds = np.zeros(bits, bool), [], None
        lap("traversing")
        for kind, owner, n_bits, payload, slots in zip(*(inbox.column(x).to_pylist() for x in ("kind", "owner", "n_bits", "payload", "slots")), strict=True):
            if kind == "state":
                visited = np.unpackbits(np.frombuffer(payload, np.uint8), count=bits).astype(bool)
            elif kind == "seed":
                seeds = np.unique(np.array(slots, np.int64))
            else:
                mail.append((owner, n_bits, payload))
        if mail:
            owners, lengths, payloads = zip(*mail, strict=True)
            which, slots = decode_many(plan.codec, payloads, lengths)
            arrived = np.array(owners, np.int64)[which] * plan.size + slots
        lap("compression_sieve")
        if seeds is not None:
            best = np.full(bits, -1, np.int64)
            best[seeds] = block * plan.size + seeds
        elif mail:
            best = _candidates(static, arrived, bits, plan.combine)
        else:
            best = np.full(bits, -1, np.int64)
        lap("traversing")
        fresh = (best >= 0) & ~visited
        new = np.flatnonzero(fresh)
        visited |= fresh
        if visited.any():
            out.add(block, "state", block, bits, None, np.packbits(visited).tobytes())
        if len(new):
            out.add(block, "found", block, bits, len(new), None, new.astype(np.int32), best[new])
        lap("reducing")
        if plan.asks:
            for needers, _, _ in static.needs:  # the vectors are told apart by owner here: whom to ask
                for owner in needers.tolist():
                    out.add(owner, "request", block, plan.bits(owner), None, b"\0" * 8)
        elif len(new) and plan.sieved:
            for needers, slots, ends in _sieved(static, fresh):
                some = np.flatnonzero(np.diff(ends))
                ends = np.append(ends[some], ends[-1])
                for needer, n, payload in zip(needers[some].tolist(), np.diff(ends).tolist(), encode_many(plan.codec, slots, ends, bits), strict=True):
                    out.add(needer, "message", block, bits, n, payload)
        elif len(new):
            out.add(-1, "message", block, bits, len(new), CODECS[plan.codec][0](new, bits))
        lap("compression_sieve")
        for phase, seconds in spent.items():
            out.add(block, phase, block, None, int(seconds * 1e6))
        return out.table()

    return run


def replier(plan: Plan):
    """The second step of a level when frontiers are asked for: each request is answered with what the needer's vector leaves of the
    frontier, be it nothing."""

    def run(key, static_rows: pa.Table, inbox: pa.Table) -> pa.Table:
        block = key[0].as_py()
        bits, out, began = plan.bits(block), _Out(), time.perf_counter()
        fresh, asked = np.zeros(bits, bool), set()
        for kind, owner, slots in zip(*(inbox.column(x).to_pylist() for x in ("kind", "owner", "slots")), strict=True):
            if kind == "found":
                fresh[np.array(slots, np.int64)] = True
            else:
                asked.add(owner)
        for needers, slots, ends in _sieved(_Static(static_rows), fresh):
            for needer, n, payload in zip(needers.tolist(), np.diff(ends).tolist(), encode_many(plan.codec, slots, ends, bits), strict=True):
                if needer in asked:
                    out.add(needer, "message", block, bits, n, payload)
        out.add(block, "compression_sieve", block, None, int((time.perf_counter() - began) * 1e6))
        return out.table()

    return run


# ---------------------------------------------------------------------------------------------------------------------
# the search


@dataclass
class Outcome:
    tree: DataFrame
    ledger: DataFrame
    seconds: list[tuple[int, str, float]] = field(default_factory=list)
    sizes: list[int] = field(default_factory=list)


def level_plan(g: GraphLayout, static: DataFrame, rows: DataFrame, step) -> DataFrame:
    """One level: rows meet their block. A message to all (to_block -1) gets a copy for every block, on the way into the exchange."""
    every = F.sequence(F.lit(0).cast("long"), F.lit(g.blocks - 1).cast("long"))
    to = F.explode(F.when(F.col("to_block") < 0, every).otherwise(F.array("to_block"))).alias("to_block")
    inbox = rows.select(to, *_NAMES[1:]).repartition(tasks_of(g), "to_block")
    return static.groupBy("block").cogroup(inbox.groupBy("to_block")).applyInArrow(step, ROW)


def search(g: GraphLayout, seeds: list[int], codec: str, needs: DataFrame | None, combine: str = "max", max_level: int | None = None, target: int | None = None, asks: bool = False) -> Outcome:
    """Breadth-first from the seeds. needs: the directory, or None for messages to all. asks: by requests and replies."""
    spark = g.spark
    folder = f"{shared_dir(spark)}/search-{uuid.uuid4().hex}"
    plan = Plan(g.size, g.n, codec, needs is not None, combine, asks)
    columns = program(g, _asked(g, needs) if asks else needs)
    static = program(g, needs, edges=False) if asks else columns
    cores = max(1, min(spark.sparkContext.defaultParallelism, tasks_of(g)))
    by_block: dict[int, list[int]] = {}
    for s in seeds:
        by_block.setdefault(s // g.size, []).append(s % g.size)
    rows = spark.createDataFrame([(b, "seed", b, None, None, None, own, None) for b, own in by_block.items()], ROW)
    seconds, counts, level, sent = [], [], 0, 0
    while True:
        began = time.perf_counter()
        stages = [("steps", columns, rows, expander(plan))]
        own = dict.fromkeys(("found", *PHASES), 0)
        for name, held, inbox, step in stages:
            path = f"{folder}/{name}/level={level}"
            seen = Observation()
            sums = [F.sum(F.when(F.col("kind") == x, F.col("n_set"))).alias(x) for x in own]
            level_plan(g, held, inbox, step).observe(seen, *sums).write.parquet(path)
            for x, n in seen.get.items():
                own[x] += n or 0
            if asks and name == "steps":  # the state stays with its block while requests and replies go round
                made = spark.read.schema(ROW).parquet(path)
                stages.append(("replies", static, made.where("kind in ('request', 'found')"), replier(plan)))
        spent = {p: own[p] / 1e6 / cores for p in PHASES}
        seconds += [(level, p, s) for p, s in spent.items()] + [(level, "communication", max(0.0, time.perf_counter() - began - sum(spent.values())))]
        if not own["found"]:
            break
        counts.append(own["found"])
        step = spark.read.schema(ROW).parquet(f"{folder}/steps/level={level}")
        if (max_level is not None and level >= max_level) or (target is not None and level and _holds(g, step, target)):
            break
        sent = level + 1  # what this level made is sent: it counts in the ledger
        rows = step.where("kind in ('state', 'message')")
        if asks:
            rows = rows.unionByName(spark.read.schema(ROW).parquet(f"{folder}/replies/level={level}").where("kind = 'message'"))
        level += 1
    every = spark.read.schema(f"{ROW}, level long").parquet(f"{folder}/steps")
    found = every.where("kind = 'found'").select("owner", "level", F.inline(F.arrays_zip("slots", "parents")))
    tree = _written(found.select((F.col("owner") * g.size + F.col("slots")).alias("vid"), "level", F.col("parents").alias("parent")), f"{folder}/tree")
    made = every if not asks else every.unionByName(spark.read.schema(f"{ROW}, level long").parquet(f"{folder}/replies"))
    ledger = _written(_ledger(g, made.where(F.col("level") < sent)), f"{folder}/ledger")
    delete(spark, f"{folder}/steps")
    delete(spark, f"{folder}/replies")
    return Outcome(tree, ledger, seconds, counts)


def _holds(g: GraphLayout, step: DataFrame, vid: int) -> bool:
    return not step.where((F.col("kind") == "found") & (F.col("owner") == vid // g.size) & F.array_contains("slots", vid % g.size)).isEmpty()


def _ledger(g: GraphLayout, rows: DataFrame) -> DataFrame:
    """A row for each message between different blocks; copies of a message to all are counted without being made."""
    sent = rows.where("kind in ('message', 'request')").select("level", "to_block", "kind", "owner", "n_bits", "n_set", F.octet_length("payload").cast("long").alias("bytes"))
    every = F.sequence(F.lit(0).cast("long"), F.lit(g.blocks - 1).cast("long"))
    sent = sent.withColumn("to_block", F.explode(F.when(F.col("to_block") < 0, every).otherwise(F.array("to_block")))).where("to_block <> owner")
    asked = F.col("kind") == "request"  # a request goes from the needer to the owner
    return sent.select(
        "level",
        F.when(asked, F.col("to_block")).otherwise(F.col("owner")).alias("owner_block"),
        F.when(asked, F.col("owner")).otherwise(F.col("to_block")).alias("needer_block"),
        F.when(asked, "request").otherwise("reply").alias("direction"),
        F.coalesce("n_set", F.lit(0)).cast("long").alias("n_set"),
        sizes.bitmap_bytes(F.col("n_bits")).alias("raw_bytes"),
        "bytes",
    )


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _written(df: DataFrame, path: str) -> DataFrame:
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
