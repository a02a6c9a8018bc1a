"""Queries of the searches: trees by every method, directories, products and applications."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import apps, directory as d, exchange as x, spmv as m
from ..operators.traverse import METHODS, PULLS, bfs, bfs_many, path_counts
from ..sources.graphs import GRAPHS, NAMED
from ..sources.tables import load
from . import sqlgen as q
from .registry import directory, graph, register, run, tree

TREE_COLUMNS = "SELECT vid, level, parent FROM tree"

for name in NAMED:
    register(f"tree_{name}", lambda s, sf, name=name: tree(s, sf, name).select("vid", "level", "parent"), q.chain_sql() if name == "event_chain" else q.tree_sql(name))

# every way to run the flagship search gives the flagship tree
for method in (*METHODS, *PULLS):
    register(f"tree_{method}_order_part", lambda s, sf, method=method: run(s, sf, "order_part", method).tree, q.tree_sql("order_part"))
register("tree_grid_2d_order_part", lambda s, sf: run(s, sf, "order_part", "grid_2d").tree, q.tree_sql("order_part"))
register("tree_grid_3x2_order_part", lambda s, sf: bfs(graph(s, sf, "order_part"), method="grid_2d", grid=(3, 2)).tree, q.tree_sql("order_part"))
register("tree_auto_kron", lambda s, sf: bfs(graph(s, sf, "kron"), method="auto").tree, q.tree_sql("kron"))
register("tree_auto_order_part", lambda s, sf: run(s, sf, "order_part", "auto").tree, q.tree_sql("order_part"))
register("tree_max_level_2", lambda s, sf: bfs(graph(s, sf, "order_part"), max_level=2).tree, q.tree_sql("order_part", depth=2))

register("tree_min_order_part", lambda s, sf: bfs(graph(s, sf, "order_part"), combine_by="min").tree, q.tree_sql("order_part", combine="min"))
register("reach_hierarchy", lambda s, sf: bfs(graph(s, sf, "hierarchy"), parents=False).tree, q.tree_sql("hierarchy", "SELECT vid, level FROM tree"))
register(
    "unreached_hierarchy",
    lambda s, sf: graph(s, sf, "hierarchy").vertices().select("vid").join(tree(s, sf, "hierarchy"), "vid", "left").select("vid", "level"),
    q.tree_sql("hierarchy", "SELECT CAST(i AS BIGINT) AS vid, tree.level FROM g, range((SELECT n FROM g)) r(i) LEFT JOIN tree ON tree.vid = i"),
)
register("tree_multi_source", lambda s, sf: bfs(graph(s, sf, "order_part"), [0, 5, 77]).tree, q.tree_sql("order_part", sources=["0", "5", "77"]))
ROOTS = (0, 1, 2, 3, 5, 8, 13, 21)
register(
    "w14_many_roots",
    lambda s, sf: bfs_many(graph(s, sf, "kron"), list(ROOTS)),
    " UNION ALL ".join(f"SELECT * FROM ({q.tree_sql('kron', f'SELECT CAST({r} AS BIGINT) AS root, vid, level, parent FROM tree', sources=[str(r)])}) r{r}" for r in ROOTS),
)


def _paths_sql(name: str) -> str:
    depth = GRAPHS[name].depth
    ctes = q.base(name) + q.levels(name) + ["p0 AS MATERIALIZED (SELECT vid, CAST(1 AS BIGINT) AS n_paths FROM l0)"]
    for k in range(1, depth + 1):
        ctes.append(f"p{k} AS MATERIALIZED (SELECT l{k}.vid, CAST(sum(p{k - 1}.n_paths) AS BIGINT) AS n_paths FROM l{k} JOIN e ON e.dst = l{k}.vid JOIN p{k - 1} ON p{k - 1}.vid = e.src GROUP BY l{k}.vid)")
    every = " UNION ALL ".join(f"SELECT vid, CAST({k} AS BIGINT) AS level, n_paths FROM p{k}" for k in range(depth + 1))
    return q.query(ctes, every)


register("paths_order_part", lambda s, sf: path_counts(graph(s, sf, "order_part")), _paths_sql("order_part"))

# ---------------------------------------------------------------------------------------------------------------------
# directories

for name in ("order_part", "star", "kron", "toy8"):
    register(f"needs_{name}", lambda s, sf, name=name: directory(s, sf, name), q.query(q.base(name), "SELECT needer_block, owner_block, slot FROM needs"))
    register(
        f"needs_setup_{name}",
        lambda s, sf, name=name: d.directory_setup_ledger(graph(s, sf, name), directory(s, sf, name)),
        q.query(q.base(name), "SELECT n.block AS needer_block, o.block AS owner_block, (o.n_bits + 7) // 8 AS bytes FROM blk o, blk n WHERE o.block <> n.block"),
    )
    register(
        f"receivers_{name}",
        lambda s, sf, name=name: d.receiver_counts(graph(s, sf, name), directory(s, sf, name)),
        q.query(q.base(name), "SELECT owner_block * b + slot AS vid, count(*) AS receivers FROM needs, g WHERE needer_block <> owner_block GROUP BY 1"),
    )
    register(
        f"receivers_bound_{name}",
        lambda s, sf, name=name: d.receiver_bounds(graph(s, sf, name), directory(s, sf, name)),
        q.query(
            q.base(name),
            "SELECT r.vid, r.receivers, least(dg.degree, nb.blocks - 1) AS bound, r.receivers <= least(dg.degree, nb.blocks - 1) AS ok FROM (SELECT owner_block * b + slot AS vid, count(*) AS receivers FROM needs, g WHERE needer_block <> owner_block GROUP BY 1) r JOIN (SELECT src AS vid, count(*) AS degree FROM e GROUP BY src) dg ON dg.vid = r.vid, nb",
        ),
    )
    register(
        f"sieve_ratio_{name}",
        lambda s, sf, name=name: d.sieve_ratio(graph(s, sf, name), tree(s, sf, name), directory(s, sf, name)),
        q.tree_sql(
            name,
            "SELECT a.level, a.n * (blocks - 1) AS plain, coalesce(c.s, 0) AS sieved, round(coalesce(c.s, 0)::DOUBLE / greatest(a.n * (blocks - 1), 1), 6) AS ratio FROM nb, (SELECT level, count(*) AS n FROM tree GROUP BY level) a LEFT JOIN (SELECT level, count(*) AS s FROM tree, g, needs WHERE needs.owner_block = vid // b AND needs.slot = vid % b AND needer_block <> owner_block GROUP BY level) c ON c.level = a.level",
        ),
    )
for codec in ("bitmap", "wah"):
    members = "SELECT needer_block, owner_block, slot, n_bits FROM needs JOIN blk ON block = owner_block"
    frame = "SELECT DISTINCT needer_block, owner_block, n_bits FROM needs JOIN blk ON block = owner_block"
    register(
        f"needs_packed_{codec}_order_part",
        lambda s, sf, codec=codec: d.pack_needs(graph(s, sf, "order_part"), directory(s, sf, "order_part"), codec),
        q.query(q.base("order_part"), f"SELECT needer_block, owner_block, n_set, bytes FROM ({q.sized_sql(members, frame, ['needer_block', 'owner_block'], codec)}) z"),
    )
register(
    "needs_native_bitmaps",
    lambda s, sf: d.native_bitmaps(directory(s, sf, "order_part")).select("needer_block", "owner_block", "bucket", "n_set"),
    q.query(q.base("order_part"), "SELECT needer_block, owner_block, CAST(1 + slot // 32768 AS BIGINT) AS bucket, count(*) AS n_set FROM needs GROUP BY ALL"),
)
register(
    "needs_profile_order_part",
    lambda s, sf: d.directory_profile(directory(s, sf, "order_part"), graph(s, sf, "order_part").blocks),
    q.query(q.base("order_part"), "SELECT needer_block, " + ", ".join(f"count(*) FILTER (owner_block = {i}) AS o{i}" for i in range(8)) + " FROM needs GROUP BY needer_block"),
)
register("needs_row_view", lambda s, sf: d.needs_of(directory(s, sf, "order_part"), 3), q.query(q.base("order_part"), "SELECT needer_block, owner_block, slot FROM needs WHERE needer_block = 3"))
register("needs_column_view", lambda s, sf: d.needed_from(directory(s, sf, "order_part"), 3), q.query(q.base("order_part"), "SELECT needer_block, owner_block, slot FROM needs WHERE owner_block = 3"))


def _needs_delta(s, sf):
    """The directory after a third of the edges were taken away and half of these put back."""
    g = graph(s, sf, "user_hour")
    gone, back = g.edges.where("(src + dst) % 3 = 0"), g.edges.where("(src + dst) % 6 = 0")
    less = d.apply_edge_delta(g, d.needs_counts(g, g.edges), None, gone)
    return d.apply_edge_delta(g, less, back, None).select("needer_block", "owner_block", "slot", "edges")


register("needs_delta_events", _needs_delta, q.query(q.base("user_hour"), "SELECT dst // b AS needer_block, src // b AS owner_block, src % b AS slot, count(*) AS edges FROM e, g WHERE (src + dst) % 3 <> 0 OR (src + dst) % 6 = 0 GROUP BY ALL"))

# the worked examples
register("w9_toy_tree", lambda s, sf: tree(s, sf, "toy8"), q.tree_sql("toy8"))
register(
    "w9_toy_spmv",
    lambda s, sf: m.combine(m.expand(graph(s, sf, "toy8"), tree(s, sf, "toy8").where("level = 1"))).select("vid", "parent"),
    q.tree_sql("toy8", "SELECT e.dst AS vid, max(e.src) AS parent FROM e JOIN tree ON e.src = tree.vid WHERE tree.level = 1 GROUP BY e.dst"),
)
register("w10_toy_directory", lambda s, sf: directory(s, sf, "toy8").where("needer_block = 3 AND owner_block = 1").select("slot"), q.query(q.base("toy8"), "SELECT slot FROM needs WHERE needer_block = 3 AND owner_block = 1"))
register(
    "w10_toy_sieve",
    lambda s, sf: d.sieve(graph(s, sf, "toy8"), tree(s, sf, "toy8").where("level = 1"), directory(s, sf, "toy8")).where("needer_block = 3 AND owner_block = 1").select("vid"),
    q.tree_sql("toy8", "SELECT vid FROM tree, g, needs WHERE level = 1 AND needs.owner_block = vid // b AND needs.slot = vid % b AND needer_block = 3 AND owner_block = 1"),
)
register(
    "w11_toy_pull",
    lambda s, sf: x.pull_ledger(graph(s, sf, "toy8"), tree(s, sf, "toy8"), directory(s, sf, "toy8"), "bitmap").where("needer_block = 1 AND owner_block = 0").select("level", "direction", "n_messages", "bytes"),
    q.with_ledger("toy8", "bitmap", True, "SELECT level, unnest(['reply', 'request']) AS direction, CAST(1 AS BIGINT) AS n_messages, unnest([bytes, 8]) AS bytes FROM book WHERE needer_block = 1 AND owner_block = 0"),
)

# ---------------------------------------------------------------------------------------------------------------------
# products


def _vector(s, sf):
    """Whole quantities of each part of the part-supplier graph, as an integer vector."""
    return load(s, sf, "lineitem", "l_partkey", "l_quantity").groupBy(F.col("l_partkey").cast("long").alias("vid")).agg(F.sum(F.col("l_quantity").cast("long")).alias("val"))


_VECTOR = "x AS MATERIALIZED (SELECT l_partkey AS vid, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS val FROM lineitem GROUP BY 1)"
_PRODUCT = "SELECT e.dst AS vid, CAST({agg} AS BIGINT) AS y FROM e JOIN x ON x.vid = e.src GROUP BY e.dst"
for label, semiring, agg in (("sum", "plus_times", "sum(val)"), ("maxplus", "max_plus", "max(val + 1)"), ("minplus", "min_plus", "min(val + 1)")):
    register(f"spmv_{label}", lambda s, sf, semiring=semiring: m.spmv(graph(s, sf, "part_supplier"), _vector(s, sf), semiring), q.query(q.base("part_supplier") + [_VECTOR], _PRODUCT.format(agg=agg)))
register("spmv_sieved_sum", lambda s, sf: m.spmv(graph(s, sf, "part_supplier"), _vector(s, sf), sieved=True, needs=directory(s, sf, "part_supplier")), q.query(q.base("part_supplier") + [_VECTOR], _PRODUCT.format(agg="sum(val)")))


def _vectors(s, sf):
    return load(s, sf, "lineitem", "l_linenumber", "l_partkey", "l_quantity").groupBy(F.col("l_linenumber").cast("long").alias("vec_id"), F.col("l_partkey").cast("long").alias("vid")).agg(F.sum(F.col("l_quantity").cast("long")).alias("val"))


register("w15_spmv_many", lambda s, sf: m.spmv_many(graph(s, sf, "part_supplier"), _vectors(s, sf)), q.query(q.base("part_supplier") + [_VECTOR], _PRODUCT.format(agg="sum(val)")))


def _input_mask(s, sf):
    """Masking the input by the needer's vector changes no product, for a directed matrix too."""
    g = graph(s, sf, "event_chain")
    ones = g.vertices().select("vid", F.lit(1).cast("long").alias("val"))
    a, b = m.spmv(g, ones), m.spmv(g, ones, sieved=True)
    both = a.join(b.withColumnRenamed("y", "z"), "vid", "full_outer")
    return both.agg(F.count("*").alias("rows"), F.sum((~F.col("y").eqNullSafe(F.col("z"))).cast("long")).alias("differ"))


register("lemma_input_mask", _input_mask, q.query(q.base("event_chain"), "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS differ FROM (SELECT DISTINCT dst FROM e) d0"))


def _output_mask(s, sf):
    """Rows of the product that the opposite vector would mask: none for a symmetric matrix, some for a directed one."""
    out = None
    for name in ("order_part", "event_chain"):
        g = graph(s, sf, name)
        needs = directory(s, sf, name).select((F.col("owner_block") * g.size + F.col("slot")).alias("dst"), F.col("needer_block").alias("other"))
        rows = g.edges.select("dst", F.floor(F.col("src") / g.size).cast("long").alias("other")).distinct()
        lost = rows.join(needs, ["dst", "other"], "left_anti").agg(F.count("*").alias("lost")).select(F.lit(name).alias("graph"), "lost")
        out = lost if out is None else out.unionByName(lost)
    return out


def _output_sql(name):
    return f"SELECT * FROM ({q.query(q.base(name), f'''SELECT '{name}' AS graph, count(*) AS lost FROM (SELECT DISTINCT dst, src // b AS other FROM e, g) r0 WHERE NOT EXISTS (SELECT 1 FROM needs, g WHERE owner_block * b + slot = r0.dst AND needer_block = r0.other)''')}) o_{name}"


register("lemma_output_mask", _output_mask, _output_sql("order_part") + " UNION ALL " + _output_sql("event_chain"))

# ---------------------------------------------------------------------------------------------------------------------
# applications

register(
    "w16_hops",
    lambda s, sf: apps.hop_distance(graph(s, sf, "star"), 0, graph(s, sf, "star").vertices()),
    q.tree_sql("star", "SELECT CAST(i AS BIGINT) AS vid, tree.level AS hops FROM range((SELECT n FROM g)) r(i) LEFT JOIN tree ON tree.vid = i"),
)
register("w16_spanning_tree", lambda s, sf: apps.spanning_tree(tree(s, sf, "star")), q.tree_sql("star", "SELECT parent, vid FROM tree WHERE level > 0"))


def _components_sql(name: str, rounds: int) -> str:
    ctes = q.base(name) + ["c0 AS MATERIALIZED (SELECT CAST(i AS BIGINT) AS vid, CAST(i AS BIGINT) AS label FROM range((SELECT n FROM g)) r(i))"]
    for k in range(rounds):
        ctes.append(f"a{k} AS MATERIALIZED (SELECT c.vid, least(c.label, coalesce(min(d.label), c.label)) AS low FROM c{k} c LEFT JOIN e ON e.dst = c.vid LEFT JOIN c{k} d ON d.vid = e.src GROUP BY c.vid, c.label)")
        ctes.append(f"c{k + 1} AS MATERIALIZED (SELECT a.vid, least(a.low, c.label) AS label FROM a{k} a JOIN c{k} c ON c.vid = a.low)")
    return q.query(ctes, f"SELECT vid, label AS component FROM c{rounds}")


for name in ("order_customer", "hierarchy", "links"):
    register(f"w16_components_{name}", lambda s, sf, name=name: apps.connected_components(graph(s, sf, name)), _components_sql(name, 12))


def _betweenness_sql(name: str) -> str:
    depth = GRAPHS[name].depth
    ctes = [f"pt AS MATERIALIZED ({_paths_sql(name)})"] + q.base(name)
    ctes.append(f"d{depth} AS MATERIALIZED (SELECT vid, level, n_paths, CAST(0 AS DOUBLE) AS dependency FROM pt WHERE level = {depth})")
    for k in range(depth - 1, -1, -1):
        ctes.append(
            f"d{k} AS MATERIALIZED (SELECT pt.vid, pt.level, pt.n_paths, coalesce(sum(pt.n_paths::DOUBLE / y.n_paths * (1 + y.dependency)), 0) AS dependency FROM pt LEFT JOIN (SELECT e.src, z.n_paths, z.dependency FROM e JOIN d{k + 1} z ON z.vid = e.dst) y ON y.src = pt.vid WHERE pt.level = {k} GROUP BY pt.vid, pt.level, pt.n_paths)"
        )
    return q.query(ctes, " UNION ALL ".join(f"SELECT vid, level, n_paths, round(dependency, 4) AS dependency FROM d{k}" for k in range(depth + 1)))


register("w16_betweenness_toy8", lambda s, sf: apps.betweenness_one_source(graph(s, sf, "toy8")).withColumn("dependency", F.round("dependency", 4)), _betweenness_sql("toy8"))
register("w16_betweenness_kron", lambda s, sf: apps.betweenness_one_source(graph(s, sf, "kron")).withColumn("dependency", F.round("dependency", 4)), _betweenness_sql("kron"))


def _tree_checks(s, sf):
    """Violations of a search tree's rules, by kind: all 0."""
    g = graph(s, sf, "star")
    return s.createDataFrame(sorted(apps.check_tree(g, tree(s, sf, "star"), g.source).items()), "rule string, violations long")


register("check_tree_star", _tree_checks, "SELECT unnest(['edges', 'levels', 'open', 'roots', 'spans', 'twice']) AS rule, CAST(0 AS BIGINT) AS violations")
