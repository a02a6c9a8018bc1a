"""What is built on searches: hop distances, components, spanning trees, one-source betweenness, and checks of a tree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.lineage import cut
from .layout import GraphLayout
from .traverse import bfs, path_counts


def hop_distance(g: GraphLayout, source: int, targets: DataFrame) -> DataFrame:
    """(vid, hops) of given vertices; null if unreachable."""
    return targets.select("vid").join(bfs(g, source).tree, "vid", "left").select("vid", F.col("level").alias("hops"))


def spanning_tree(tree: DataFrame) -> DataFrame:
    """(parent, vid): the tree's edges."""
    return tree.where("level > 0").select("parent", "vid")


def connected_components(g: GraphLayout) -> DataFrame:
    """(vid, component) for every id: the smallest id it is connected to. Labels travel along edges and then jump to their label's
    label, so the number of rounds is about the logarithm of the longest chain."""
    labels = cut(g.spark.range(g.n).select(F.col("id").alias("vid"), F.col("id").alias("label")))
    while True:
        near = g.edges.join(labels.select(F.col("vid").alias("src"), "label"), "src").groupBy(F.col("dst").alias("vid")).agg(F.min("label").alias("near"))
        step = labels.join(near, "vid", "left").select("vid", "label", F.least("label", F.coalesce("near", "label")).alias("low"))
        far = labels.select(F.col("vid").alias("low"), F.col("label").alias("far"))
        step = cut(step.join(far, "low").select("vid", F.col("label").alias("old"), F.least("low", "far").alias("label")))
        if step.where("old <> label").isEmpty():
            return step.select("vid", F.col("label").alias("component"))
        labels = step.select("vid", "label")


def betweenness_one_source(g: GraphLayout, source: int | None = None) -> DataFrame:
    """(vid, level, n_paths, dependency): how much each vertex lies on the shortest paths from one source, level by level from the deepest
    back."""
    counts = cut(path_counts(g, source))
    deepest = counts.agg(F.max("level")).first()[0]
    done = cut(counts.where(F.col("level") == deepest).select("vid", "level", "n_paths", F.lit(0.0).alias("dependency")))
    parts = [done]
    for level in range(deepest - 1, -1, -1):
        here = counts.where(F.col("level") == level)
        below = parts[-1].select(F.col("vid").alias("dst"), F.col("n_paths").alias("np"), "dependency")
        flow = g.edges.join(here.select(F.col("vid").alias("src"), "n_paths"), "src").join(below, "dst")
        sums = flow.groupBy(F.col("src").alias("vid")).agg(F.sum(F.col("n_paths") / F.col("np") * (1 + F.col("dependency"))).alias("d"))
        parts.append(cut(here.join(sums, "vid", "left").select("vid", "level", "n_paths", F.coalesce("d", F.lit(0.0)).alias("dependency"))))
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def check_tree(g: GraphLayout, tree: DataFrame, source: int) -> dict[str, int]:
    """Numbers of violations: roots, tree edges that don't exist, levels that don't follow, edges that span more than one level, and
    edges from reached to unreached ids. All are 0 for a right tree."""
    kids = tree.where("level > 0").select(F.col("parent").alias("src"), F.col("vid").alias("dst"), "level")
    up = tree.select(F.col("vid").alias("src"), F.col("level").alias("above"))
    a, b = tree.select(F.col("vid").alias("src"), F.col("level").alias("a")), tree.select(F.col("vid").alias("dst"), F.col("level").alias("b"))
    spans = g.edges.join(a, "src").join(b, "dst")
    return {
        "roots": tree.where((F.col("level") == 0) & (F.col("vid") == source) & (F.col("parent") == source)).count() - 1,
        "edges": kids.join(g.edges, ["src", "dst"], "left_anti").count(),
        "levels": kids.join(up, "src").where("level <> above + 1").count() + kids.join(up, "src", "left_anti").count(),
        "spans": spans.where(F.col("b") > F.col("a") + 1).count() if g.directed else spans.where(F.abs(F.col("a") - F.col("b")) > 1).count(),
        "open": g.edges.join(a, "src", "left_semi").join(b, "dst", "left_anti").count(),
        "twice": tree.count() - tree.select("vid").distinct().count(),
    }
