"""Plans of message searches, requests and replies, sinks, restarts of streams, and late data."""

import pytest
from pyspark.sql import functions as F

from graphwave.operators import blocks, spmv
from graphwave.operators.directory import build_needs
from graphwave.operators.exchange import pull_ledger
from graphwave.operators.layout import build
from graphwave.operators.traverse import METHODS, PULLS, bfs
from graphwave.plans.lineage import cut
from graphwave.plans.registry import graph, tree
from graphwave.sources.graphs import Tuples, toy8
from graphwave.sources.kronecker import kronecker_edges
from graphwave.sources.tables import load_run, read_edges, save_run, write_edges
from graphwave.streaming import stream as st


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def toy(spark):
    return build(toy8(spark), 4, name="toy8")


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_no_level_moves_an_edge(spark, tiny):
    """One exchange a level, that of the messages: nothing is exchanged between the kept edges and the program."""
    g = graph(spark, tiny, "order_part")
    for needs in (None, cut(build_needs(g))):
        static = blocks.program(g, needs)
        inbox = spark.createDataFrame([(0, "seed", 0, None, None, None, [0], None)], blocks.ROW)
        plan = plan_of(blocks.level_plan(g, static, inbox, blocks.expander(blocks.Plan(g.size, g.n, "wah", needs is not None, "max"))))
        top = plan.split("InMemoryRelation")[0] + plan[plan.rindex("REPARTITION_BY_NUM") - 60 :]
        assert "FlatMapCoGroupsInArrow" in plan and "Exchange" not in plan.split("InMemoryTableScan")[0] and top.count("Exchange") == 1, plan


def test_sieved_product_keeps_its_edges(spark, tiny):
    g = graph(spark, tiny, "part_supplier")
    x = g.vertices().select("vid", F.lit(1).cast("long").alias("val"))
    needs = cut(build_needs(g))
    assert rows(spmv.spmv(g, x, sieved=True, needs=needs)) == rows(spmv.spmv(g, x))
    most = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as for tables that are large
    try:
        plan = plan_of(spmv.spmv(g, x, sieved=True, needs=needs))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", most)
    branch = plan[: plan.index("InMemoryTableScan")]
    assert branch[branch.rindex("Join") :].count("Exchange") == 0, plan


def test_many_vectors_combine_as_one(toy):
    x = toy.vertices().select("vid", (F.col("vid") * 3).alias("val"))
    both = x.withColumn("vec_id", F.lit(1)).unionByName(x.withColumn("val", F.col("val") + 100).withColumn("vec_id", F.lit(2)))
    for semiring, last in (("max_plus", 2), ("min_plus", 1)):
        one = both.where(F.col("vec_id") == last).select("vid", "val")
        assert rows(spmv.spmv_many(toy, both, semiring)) == rows(spmv.spmv(toy, one, semiring))


@pytest.mark.parametrize("combine", ["max", "min", "count"])
def test_messages_combine_as_joins_do(spark, combine):
    g = build(Tuples(kronecker_edges(spark, 7, 4), 128, 1), 6)
    want = rows(bfs(g, combine_by=combine).tree.select("vid", "level", "parent").where("level > 0"))
    for method in ("wah_sieved", "bitmap_allgather", "wah_pull"):
        assert rows(bfs(g, method=method, combine_by=combine).tree.select("vid", "level", "parent").where("level > 0")) == want


def test_stops_and_several_sources(spark):
    g = build(Tuples(kronecker_edges(spark, 7, 2), 128, 0), 5)
    for options in ({"max_level": 2}, {"source": [3, 5, 77]}, {"max_level": 0}):
        assert rows(bfs(g, method="wah_sieved", **options).tree.select("vid", "level", "parent")) == rows(bfs(g, **options).tree.select("vid", "level", "parent"))
    deep = bfs(g).tree
    goal = deep.where("level = 2").first()["vid"]
    assert bfs(g, method="bitmap_sieved", target=goal).tree.agg(F.max("level")).first()[0] == 2
    assert bfs(g, method="auto", parents=False).tree.columns == ["vid", "level"]
    assert rows(bfs(g, method="auto").tree) == rows(deep) == rows(bfs(g, method="grid_2d", grid=(3, 2)).tree)


def test_requests_and_replies(spark, tiny):
    """What blocks ask for and get, as executed, is what the formula says, empty replies included."""
    g = graph(spark, tiny, "order_part")
    needs = cut(build_needs(g))
    run = bfs(g, method="wah_pull", needs=needs)
    want = pull_ledger(g, tree(spark, tiny, "order_part"), needs)
    assert rows(run.ledger.select("level", "owner_block", "needer_block", "direction", "bytes")) == rows(want.select("level", "owner_block", "needer_block", "direction", "bytes"))
    assert set(PULLS) & set(METHODS) == set()


def test_a_search_deletes_what_its_levels_wrote(spark, toy, tmp_path):
    from graphwave.plans.lineage import shared_dir

    root = spark._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    files = root.getFileSystem(spark._jsc.hadoopConfiguration())
    before = {x.getPath().getName() for x in files.listStatus(root)}
    bfs(toy, method="wah_pull")
    made = [x.getPath() for x in files.listStatus(root) if x.getPath().getName() not in before and x.getPath().getName().startswith("search-")]
    assert len(made) == 1 and sorted(x.getPath().getName() for x in files.listStatus(made[0])) == ["ledger", "tree"]


def test_runs_are_saved_and_read(spark, toy, tmp_path):
    path = f"file://{tmp_path}/runs"
    for name, method in (("a", "wah_sieved"), ("b", "relational")):
        save_run(bfs(toy, method=method, profile=True), path, name, method)
    assert rows(load_run(spark, path, "a")) == rows(load_run(spark, path, "b")) == rows(bfs(toy).tree)
    assert spark.read.parquet(f"{path}/ledgers").select("run_id").distinct().count() == 1
    assert {r["phase"] for r in spark.read.parquet(f"{path}/profiles").collect()} == {"traversing", "reducing", "communication", "compression_sieve"}


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "tsv", "json", "text"])
def test_edge_lists_in_every_format(spark, toy, tmp_path, fmt):
    path = f"file://{tmp_path}/edges"
    write_edges(toy.tuples, path, fmt)
    assert rows(read_edges(spark, path, fmt)) == rows(toy.tuples)


def test_a_keeper_goes_on_after_a_restart(spark, toy, monkeypatch):
    """Batches that are repeated count once, a new keeper over the same folder finds everything, and folding changes nothing."""
    monkeypatch.setattr(st.DirectoryKeeper, "FOLD", 2)
    parts = [toy.tuples.where(f"u % 4 = {k}") for k in range(4)]
    keeper = st.DirectoryKeeper(toy)
    for k in (0, 1, 1):
        keeper.apply(parts[k], k)
    later = st.DirectoryKeeper(toy, keeper.folder)
    for k in (1, 2, 3, 3):
        later.apply(parts[k], k)
    assert rows(later.counts().select("needer_block", "owner_block", "slot")) == rows(build_needs(toy))
    assert rows(st.DirectoryKeeper(toy, keeper.folder).counts()) == rows(later.counts())


def test_a_search_after_each_batch(spark, toy):
    keeper = st.SearchKeeper(8, 4, 0, spark, method="wah_sieved")
    keeper.apply(toy.tuples.where("u < 2"), 0)
    first = rows(keeper.trees.read([0]))
    assert [r[:2] for r in first] == [(0, 0), (2, 1), (3, 1), (5, 1)]
    keeper.apply(toy.tuples.where("u >= 2"), 1)
    keeper.apply(toy.tuples.where("u >= 2"), 1)
    assert rows(keeper.trees.read([1])) == rows(bfs(toy).tree)


def test_late_rows_are_counted(spark, tmp_path):
    import time

    for k, times in enumerate((["2024-01-01 10:00:00"], ["2024-01-03 10:00:00"], ["2024-01-03 10:10:00"], ["2024-01-01 07:00:00", "2024-01-03 10:30:00"])):
        made = spark.createDataFrame([(10 * k + i, t, 1, "x", 0.0, "{}") for i, t in enumerate(times)], "event_id long, ts string, user_id long, event_type string, value double, props string")
        made.withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/events.parquet")
        time.sleep(1.1)
    written, late = st.late_rows(st.tumbling(st.stream_events(spark, f"file://{tmp_path}")))
    assert late == 1 and written.agg(F.sum("n")).first()[0] in (1, 2, 3)
