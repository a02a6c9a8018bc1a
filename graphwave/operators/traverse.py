"""Level-synchronous searches: the relational way, every message way, the two-dimensional and the two-directional way.

All of them return the same (vid, level, parent), where a vertex's parent is the largest neighbour in the level before. Message searches
run as programs of blocks (`blocks`). In the others each level is one plan whose result is written to the shared folder; the edges stay
where they are, only frontiers and candidates move.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.lineage import BROADCAST_ROWS, cut, gated
from . import blocks
from .directory import build_needs
from .layout import GraphLayout
from .spmv import combine

#: Method: codec and whether a directory sieves.
METHODS = {
    "bitmap_allgather": ("bitmap", False),
    "sparse_allgather": ("sparse", False),
    "wah_allgather": ("wah", False),
    "zlib1_allgather": ("zlib1", False),
    "zlib6_allgather": ("zlib6", False),
    "zlib9_allgather": ("zlib9", False),
    "sparse_zlib_allgather": ("sparse_zlib", False),
    "bitmap_sieved": ("bitmap", True),
    "sparse_sieved": ("sparse", True),
    "wah_sieved": ("wah", True),
    "zlib1_sieved": ("zlib1", True),
    "zlib6_sieved": ("zlib6", True),
    "zlib9_sieved": ("zlib9", True),
}

#: Methods in which a block asks for what it needs: codec of the replies.
PULLS = {"bitmap_pull": "bitmap", "wah_pull": "wah"}


@dataclass
class Run:
    """A search's tree, the ledger of its payloads, seconds by (level, phase), and the frontier sizes."""

    tree: DataFrame
    ledger: DataFrame | None = None
    seconds: list[tuple[int, str, float]] = field(default_factory=list)
    sizes: list[int] = field(default_factory=list)

    def profile(self, run_id: str, method: str) -> DataFrame:
        rows = [(run_id, method, level, phase, s) for level, phase, s in self.seconds]
        return self.tree.sparkSession.createDataFrame(rows, "run_id string, method string, level int, phase string, seconds double")


def _seed(g: GraphLayout, sources) -> DataFrame:
    ids = [sources] if isinstance(sources, int) else list(sources)
    return g.spark.createDataFrame([(int(s), 0, int(s)) for s in ids], "vid long, level long, parent long")


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _near(g: GraphLayout, levels: list[DataFrame], sizes: list[int], broadcast_rows: int, *keys: str) -> DataFrame:
    """What the next level must not hold: a neighbour of a level is in the level before, in it or behind it, so two levels are enough,
    unless edges are directed."""
    last = len(levels) if g.directed else 2
    return gated(_union([x.select(*keys) for x in levels[-last:]]), sum(sizes[-last:]), broadcast_rows)


def bfs(g: GraphLayout, source=None, method: str = "relational", combine_by: str = "max", max_level: int | None = None, target: int | None = None, profile: bool = False, needs: DataFrame | None = None, broadcast_rows: int = BROADCAST_ROWS, grid: tuple[int, int] = (2, 2), parents: bool = True) -> Run:
    """source: one id or several. method: relational, auto (two-directional), grid_2d (of grid cells), one of METHODS or of PULLS.
    combine_by: how a vertex's neighbours in the level before combine to `parent`: max, min or count. parents=False: (vid, level) only. profile:
    keep the seconds of each phase. broadcast_rows: ids up to which relational searches broadcast a counted frontier."""
    source = g.source if source is None else source
    if method in METHODS or method in PULLS:
        run = _by_messages(g, source, method, combine_by, max_level, target, profile, needs)
    else:
        run = _by_joins(g, source, method, combine_by, max_level, target, broadcast_rows, grid)
    if not parents:
        run.tree = run.tree.select("vid", "level")
    return run


def _by_messages(g, source, method, combine_by, max_level, target, profile, needs) -> Run:
    if g.n == 0:
        return Run(_seed(g, source).limit(0))
    codec, sieved = METHODS.get(method) or (PULLS[method], True)
    if sieved and needs is None:
        needs = g.extra.get("needs")
        if needs is None:
            needs = g.extra["needs"] = cut(build_needs(g).repartition("owner_block"))
    ids = [source] if isinstance(source, int) else list(source)
    found = blocks.search(g, ids, codec, needs if sieved else None, combine_by, max_level, target, asks=method in PULLS)
    ledger = found.ledger if method in PULLS else found.ledger.drop("direction")
    return Run(found.tree, ledger, found.seconds if profile else [], found.sizes)


def _by_joins(g, source, method, combine_by, max_level, target, broadcast_rows, grid) -> Run:
    start = cut(_seed(g, source))
    if g.n == 0:
        return Run(start.limit(0))
    levels, sizes, level = [start], [start.count()], 0
    waiting = None
    while sizes[-1] and (max_level is None or level < max_level):
        frontier = levels[-1].select("vid")
        visited = _near(g, levels, sizes, broadcast_rows, "vid")
        if method == "grid_2d":
            found = _grid_step(g, frontier, combine_by, *grid)
        elif method == "auto" and combine_by != "count" and (waiting is not None or _backwards_pays(g, frontier, sizes)):
            found, waiting = _backward_step(g, levels, frontier, waiting, combine_by)
        else:
            step = g.edges.join(gated(frontier.withColumnRenamed("vid", "src"), sizes[-1], broadcast_rows), "src")
            found = combine(step.select("dst", "src"), combine_by)
        level += 1
        new = cut(found.join(visited, "vid", "left_anti").select("vid", F.lit(level).cast("long").alias("level"), "parent"))
        n = new.count()
        sizes.append(n)
        if n:
            levels.append(new)
        if target is not None and n and not new.where(F.col("vid") == target).isEmpty():
            break
    return Run(_union(levels), None, [], sizes[: len(levels)])


def _backwards_pays(g: GraphLayout, frontier: DataFrame, sizes: list[int]) -> bool:
    """Whether the edges that leave the frontier outnumber a fourteenth of those that could still be looked at from the other side."""
    if g.directed or sum(sizes) * 20 < g.n:
        return False
    out = g.edges.join(gated(frontier.withColumnRenamed("vid", "src"), sizes[-1]), "src", "left_semi").count()
    return out * 14 > g.m


def _backward_step(g: GraphLayout, levels: list[DataFrame], frontier: DataFrame, waiting: DataFrame | None, combine_by: str):
    """Looks from the open ids into the frontier. Only edges whose far end is still open are read, and those that have met the frontier
    are dropped, so each later level reads less. Returns candidates and the edges that wait."""
    seen = _union([x.select(F.col("vid").alias("dst")) for x in levels])
    mine = g.edges.join(seen, "dst", "left_anti") if waiting is None else waiting
    marked = cut(mine.join(frontier.select(F.col("vid").alias("src"), F.lit(True).alias("hit")), "src", "left"))
    found = combine(marked.where("hit").select("dst", "src"), combine_by)
    # an id that is found now needs its other edges no more, nor does an edge lead anywhere whose far end was settled before
    rest = marked.where("hit is null").join(found.select(F.col("vid").alias("dst")), "dst", "left_anti").select("src", "dst")
    return found, rest


def _grid_step(g: GraphLayout, frontier: DataFrame, combine_by: str, rows: int = 2, cols: int = 2) -> DataFrame:
    """Frontier ids expand along grid columns to the cells that hold their edges; each cell's candidates fold to their owner. The cells'
    edges are dealt by cell and source once and stay."""
    br, bc = -(-g.n // rows), -(-g.n // cols)
    cells = g.extra.get(("cells", rows, cols))
    if cells is None:
        placed = g.edges.withColumns({"row": F.floor(F.col("dst") / br).cast("long"), "col": F.floor(F.col("src") / bc).cast("long")})
        cells = g.extra["cells", rows, cols] = placed.repartition(blocks.tasks_of(g), "row", "col", "src").persist(StorageLevel.MEMORY_AND_DISK)
    sent = frontier.select(F.col("vid").alias("src"), F.floor(F.col("vid") / bc).cast("long").alias("col"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(rows - 1).cast("long"))).alias("row"))
    partial = cells.join(sent.repartition(blocks.tasks_of(g), "row", "col", "src"), ["row", "col", "src"])
    agg = {"max": F.max, "min": F.min}.get(combine_by)
    if agg is None:
        return combine(partial.select("dst", "src"), combine_by)
    at_cell = partial.groupBy("row", "col", "dst").agg(agg("src").alias("best"))
    return at_cell.groupBy(F.col("dst").alias("vid")).agg(agg("best").alias("parent"))


def path_counts(g: GraphLayout, source: int | None = None) -> DataFrame:
    """(vid, level, n_paths): how many shortest paths lead to each vertex."""
    source = g.source if source is None else source
    now = cut(g.spark.createDataFrame([(source, 0, 1)], "vid long, level long, n_paths long"))
    levels, n, level, counts = [now], 1, 0, [1]
    while n:
        level += 1
        step = g.edges.join(gated(levels[-1].select(F.col("vid").alias("src"), "n_paths"), n), "src")
        found = step.groupBy(F.col("dst").alias("vid")).agg(F.sum("n_paths").alias("n_paths"))
        visited = _near(g, levels, counts, BROADCAST_ROWS, "vid")
        now = cut(found.join(visited, "vid", "left_anti").select("vid", F.lit(level).cast("long").alias("level"), "n_paths"))
        n = now.count()
        counts.append(n)
        if n:
            levels.append(now)
    return _union(levels)


def bfs_many(g: GraphLayout, roots: list[int]) -> DataFrame:
    """(root, vid, level, parent): one search for each root, all in the same level loop."""
    now = cut(g.spark.createDataFrame([(int(r), int(r), 0, int(r)) for r in roots], "root long, vid long, level long, parent long"))
    levels, n, level, counts = [now], len(roots), 0, [len(roots)]
    while n:
        level += 1
        step = g.edges.join(gated(levels[-1].select("root", F.col("vid").alias("src")), n), "src")
        found = step.groupBy("root", F.col("dst").alias("vid")).agg(F.max("src").alias("parent"))
        visited = _near(g, levels, counts, BROADCAST_ROWS, "root", "vid")
        now = cut(found.join(visited, ["root", "vid"], "left_anti").select("root", "vid", F.lit(level).cast("long").alias("level"), "parent"))
        n = now.count()
        counts.append(n)
        if n:
            levels.append(now)
    return _union(levels)
