from collections import deque

import pytest

from graphwave.operators import apps
from graphwave.operators.directory import Directory, apply_edge_delta, build_needs, needs_counts, receiver_counts
from graphwave.operators.exchange import ledger
from graphwave.operators.layout import build, load_layout, relabel, save_layout
from graphwave.operators.traverse import METHODS, bfs, bfs_many
from graphwave.plans import costs
from graphwave.plans.registry import graph, tree
from graphwave.sources.graphs import Tuples, toy8
from graphwave.sources.kronecker import KroneckerSource, edge_of, kronecker_edges


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def plain_search(edges, source):
    near = {}
    for s, d in edges:
        near.setdefault(s, []).append(d)
    level, queue = {source: 0}, deque([source])
    while queue:
        v = queue.popleft()
        for w in near.get(v, ()):
            if w not in level:
                level[w] = level[v] + 1
                queue.append(w)
    parent = {v: max(u for u in level if v in near.get(u, ()) and level[u] == k - 1) if k else v for v, k in level.items()}
    return sorted((v, k, parent[v]) for v, k in level.items())


@pytest.fixture(scope="module")
def toy(spark):
    return build(toy8(spark), 4, name="toy8")


TOY_TREE = [(0, 0, 0), (1, 3, 7), (2, 1, 0), (3, 1, 0), (4, 2, 2), (5, 1, 0), (6, 2, 3), (7, 2, 5)]


@pytest.mark.parametrize("method", ["relational", "grid_2d", "auto", *METHODS])
def test_every_method_gives_the_toy_tree(toy, method):
    assert rows(bfs(toy, 0, method).tree.select("vid", "level", "parent")) == TOY_TREE


@pytest.mark.parametrize("method", ["relational", "bitmap_allgather", "wah_allgather", "zlib6_allgather", "wah_sieved"])
def test_searches_without_broadcasts(toy, method):
    assert rows(bfs(toy, 0, method, broadcast_rows=0).tree.select("vid", "level", "parent")) == TOY_TREE


def test_toy_directory(toy):
    needs = build_needs(toy)
    got = {}
    for n, o, s in rows(needs):
        got.setdefault(o * 2 + s, set()).add(n)
    assert got == {0: {1, 2}, 1: {3}, 2: {0, 2}, 3: {0, 2, 3}, 4: {1, 3}, 5: {0, 1, 3}, 6: {0, 1}, 7: {0, 2}}
    assert sum(r[1] for r in rows(receiver_counts(toy, needs))) == 17


def test_toy_deliveries(toy):
    found = bfs(toy, 0).tree
    plain = ledger(toy, found, "sparse")
    sieved = ledger(toy, found, "sparse", build_needs(toy))
    by = lambda df: [r["n"] for r in df.groupBy("level").agg({"n_set": "sum"}).withColumnRenamed("sum(n_set)", "n").orderBy("level").collect()]
    assert by(plain) == [3, 9, 9, 3]
    assert by(sieved) == [2, 8, 6, 1]


@pytest.mark.parametrize("p", [1, 2, 3, 8])
def test_blocks_do_not_change_the_tree(spark, p):
    g = build(toy8(spark), p)
    assert rows(bfs(g, 0, "wah_sieved").tree.select("vid", "level", "parent")) == TOY_TREE


def test_random_graph_against_plain_search(spark):
    df = kronecker_edges(spark, 6, 2)
    g = build(Tuples(df, 64, 0), 5)
    assert rows(bfs(g).tree.select("vid", "level", "parent")) == plain_search(rows(g.edges), 0)


def test_payload_bytes_equal_the_set_lane(spark, tiny):
    g = graph(spark, tiny, "order_part")
    needs = build_needs(g)
    for method in ("wah_sieved", "wah_allgather", "sparse_sieved", "bitmap_sieved"):
        codec, sieved = METHODS[method]
        real = rows(bfs(g, method=method).ledger.select("level", "owner_block", "needer_block", "n_set", "bytes"))
        formula = rows(ledger(g, tree(spark, tiny, "order_part"), codec, needs if sieved else None, skip_empty=True).select("level", "owner_block", "needer_block", "n_set", "bytes"))
        assert real == formula, method


def test_compression_and_sieve_save_bytes(spark, tiny):
    """Word-aligned runs beat plain bitmaps, and the sieve beats that, on the flagship graph."""
    g = graph(spark, tiny, "order_part")
    needs = build_needs(g)
    t = tree(spark, tiny, "order_part")
    total = {}
    for codec in ("bitmap", "wah"):
        for sieve in (None, needs):
            total[codec, sieve is not None] = ledger(g, t, codec, sieve).groupBy().sum("bytes").first()[0]
    assert total["wah", True] < total["wah", False] < total["bitmap", False] == total["bitmap", True]
    factor = lambda sieve: costs.compression_factor(ledger(g, t, "wah", sieve)).first()["factor"]
    assert factor(needs) < factor(None) < 1


def test_relabelling_permutes_levels(spark, tiny):
    g = graph(spark, tiny, "order_part")
    h = relabel(g, 7919)
    to = {v: (v * 7919 + 17) % g.n for v in range(g.n)}
    assert sorted((to[v], k) for v, k, _ in rows(tree(spark, tiny, "order_part").select("vid", "level", "parent"))) == rows(bfs(h).tree.select("vid", "level"))


def test_tree_rules(spark, tiny):
    for name in ("order_part", "star", "hierarchy"):
        g = graph(spark, tiny, name)
        assert set(apps.check_tree(g, tree(spark, tiny, name), g.source).values()) == {0}


def test_empty_graph_and_unknown_source(spark, tiny):
    g = graph(spark, tiny, "bench_doc")
    assert rows(bfs(g).tree.select("vid")) == [] if g.n == 0 else True
    lone = build(Tuples(spark.createDataFrame([], "u long, v long"), 5, 3), 2)
    assert rows(bfs(lone, method="wah_sieved").tree.select("vid", "level", "parent")) == [(3, 0, 3)]


def test_duplicates_and_loops_change_nothing(spark, toy):
    more = toy.tuples.union(toy.tuples).union(spark.createDataFrame([(3, 3)], "u long, v long"))
    assert rows(bfs(build(Tuples(more, 8), 4), 0).tree.select("vid", "level", "parent")) == TOY_TREE


def test_many_roots(toy):
    one = bfs_many(toy, [0, 7])
    assert sorted(tuple(r)[1:] for r in one.where("root = 0").collect()) == TOY_TREE


def test_directory_upkeep(spark, toy):
    counts = needs_counts(toy, toy.edges)
    gone = toy.edges.where("src = 0 OR dst = 0")
    less = apply_edge_delta(toy, counts, None, gone)
    assert rows(less.select("needer_block", "owner_block", "slot")) == rows(build_needs(build(Tuples(toy.tuples.where("u <> 0"), 8), 4)))
    back = apply_edge_delta(toy, less, gone, None)
    assert rows(back.select("needer_block", "owner_block", "slot")) == rows(build_needs(toy))


def test_directory_notices_changes(spark, toy):
    d = Directory(toy)
    d.assert_static()
    other = build(Tuples(toy.tuples.where("u <> 4"), 8), 4)
    d.graph = other
    with pytest.raises(ValueError):
        d.assert_static()


def test_profile_has_every_phase(toy):
    run = bfs(toy, 0, "wah_sieved", profile=True)
    assert {p for _, p, _ in run.seconds} == {"traversing", "reducing", "communication", "compression_sieve"}
    assert run.sizes == [1, 3, 3, 1]


def test_layout_round_trip(spark, toy, tmp_path):
    save_layout(toy, f"file://{tmp_path}/g")
    assert rows(bfs(load_layout(spark, f"file://{tmp_path}/g")).tree.select("vid", "level", "parent")) == TOY_TREE


def test_kronecker_source(spark):
    spark.dataSource.register(KroneckerSource)
    want = sorted(edge_of(i, 5, 42) for i in range(2 << 5))
    assert rows(spark.read.format("kronecker").option("scale", 5).option("edgeFactor", 2).load()) == want
    assert rows(kronecker_edges(spark, 5, 2)) == want


def test_components_of_a_long_chain(spark):
    """Labels jump, so a chain of 200 takes few rounds and has one component; a second chain has its own."""
    edges = [(i, i + 1) for i in range(199)] + [(i, i + 1) for i in range(300, 320)]
    g = build(Tuples(spark.createDataFrame(edges, "u long, v long"), 321), 3)
    got = dict(rows(apps.connected_components(g)))
    assert {got[i] for i in range(200)} == {0} and {got[i] for i in range(300, 321)} == {300} and got[250] == 250
