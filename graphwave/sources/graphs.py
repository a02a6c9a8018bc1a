"""Graphs derived from the given tables. Each has a DataFrame builder and the DuckDB text of the same edge tuples.

Numeric keys get ids by offsets (the tables' keys are dense from 0); string keys get ids by rank over (kind, key), worked out from a
range partitioning, so that no task sees all keys.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.lineage import cut
from .kronecker import kronecker_edges, kronecker_sql
from .tables import load, size


@dataclass
class Tuples:
    """Edge tuples (u, v) as they come, number of vertex ids, and the search's source."""

    edges: DataFrame
    n: int
    source: int = 0


@dataclass(frozen=True)
class Graph:
    name: str
    build: Callable[[SparkSession, str], Tuples]
    tuples_sql: str
    n_sql: str
    source_sql: str = "0"
    directed: bool = False
    p: int = 4
    #: Levels that the oracle unrolls: beyond the deepest level at any given scale.
    depth: int = 10


def _counts(spark, sf_dir, *names):
    return [size(spark, sf_dir, n) for n in names]


def _pair(df: DataFrame, u, v) -> DataFrame:
    return df.select(u.cast("long").alias("u"), v.cast("long").alias("v"))


def _n(*names: str) -> str:
    return " + ".join(f"(SELECT count(*) FROM {n})" for n in names) if names else "0"


def order_part(spark, sf_dir):
    orders, parts = _counts(spark, sf_dir, "orders", "part")
    df = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    return Tuples(_pair(df, F.col("l_orderkey"), F.col("l_partkey") + orders), orders + parts)


def part_supplier(spark, sf_dir):
    parts, suppliers = _counts(spark, sf_dir, "part", "supplier")
    df = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey")
    return Tuples(_pair(df, F.col("l_partkey"), F.col("l_suppkey") + parts), parts + suppliers)


def _customer_lines(spark, sf_dir, key):
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", key)
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey)


def customer_supplier(spark, sf_dir):
    customers, suppliers = _counts(spark, sf_dir, "customer", "supplier")
    df = _customer_lines(spark, sf_dir, "l_suppkey")
    return Tuples(_pair(df, F.col("o_custkey"), F.col("l_suppkey") + customers), customers + suppliers)


def customer_part(spark, sf_dir):
    customers, parts = _counts(spark, sf_dir, "customer", "part")
    df = _customer_lines(spark, sf_dir, "l_partkey")
    return Tuples(_pair(df, F.col("o_custkey"), F.col("l_partkey") + customers), customers + parts)


def star(spark, sf_dir):
    region, nation, supplier, customer, part, orders = _counts(spark, sf_dir, "region", "nation", "supplier", "customer", "part", "orders")
    at_n, at_s = region, region + nation
    at_c = at_s + supplier
    at_p = at_c + customer
    at_o = at_p + part
    line = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    parts = [
        _pair(load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"), F.col("n_regionkey"), F.col("n_nationkey") + at_n),
        _pair(load(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), F.col("c_nationkey") + at_n, F.col("c_custkey") + at_c),
        _pair(load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), F.col("s_nationkey") + at_n, F.col("s_suppkey") + at_s),
        _pair(load(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("o_custkey") + at_c, F.col("o_orderkey") + at_o),
        _pair(line, F.col("l_orderkey") + at_o, F.col("l_partkey") + at_p),
        _pair(line, F.col("l_partkey") + at_p, F.col("l_suppkey") + at_s),
    ]
    edges = parts[0]
    for x in parts[1:]:
        edges = edges.unionByName(x)
    return Tuples(edges, at_o + orders)


_STAR_SQL = f"""
SELECT n_regionkey AS u, n_nationkey + {_n("region")} AS v FROM nation
UNION ALL SELECT c_nationkey + {_n("region")}, c_custkey + {_n("region", "nation", "supplier")} FROM customer
UNION ALL SELECT s_nationkey + {_n("region")}, s_suppkey + {_n("region", "nation")} FROM supplier
"""


def hierarchy(spark, sf_dir):
    region, nation, supplier, customer = _counts(spark, sf_dir, "region", "nation", "supplier", "customer")
    at_n, at_s = region, region + nation
    at_c = at_s + supplier
    edges = (
        _pair(load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"), F.col("n_regionkey"), F.col("n_nationkey") + at_n)
        .unionByName(_pair(load(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), F.col("c_nationkey") + at_n, F.col("c_custkey") + at_c))
        .unionByName(_pair(load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), F.col("s_nationkey") + at_n, F.col("s_suppkey") + at_s))
    )
    return Tuples(edges, at_c + customer)


def order_customer(spark, sf_dir):
    orders, customers = _counts(spark, sf_dir, "orders", "customer")
    df = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    return Tuples(_pair(df, F.col("o_orderkey"), F.col("o_custkey") + orders), orders + customers, orders)


def event_chain(spark, sf_dir):
    df = load(spark, sf_dir, "events", "event_id", "ts", "user_id")
    nxt = F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return Tuples(_pair(df.withColumn("v", nxt).where("v is not null"), F.col("event_id"), F.col("v")), size(spark, sf_dir, "events"))


def _users(spark, sf_dir):
    return load(spark, sf_dir, "events", "user_id").agg(F.max("user_id")).first()[0] + 1


def user_hour(spark, sf_dir):
    users = _users(spark, sf_dir)
    df = load(spark, sf_dir, "events", "user_id", "ts").select("user_id", F.date_trunc("hour", "ts").alias("hour"))
    hours = ranked(df.select("hour").distinct(), "hour")
    edges = df.join(hours, "hour")
    return Tuples(_pair(edges, F.col("user_id"), F.col("vid") + users), users + hours.count(), users)


def user_key(spark, sf_dir):
    users = _users(spark, sf_dir)
    df = load(spark, sf_dir, "events", "user_id", "props").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return Tuples(_pair(df, F.col("user_id"), F.col("k") + users), users + df.agg(F.max("k")).first()[0] + 1, users)


def ranked(keys: DataFrame, *by: str) -> DataFrame:
    """The distinct keys with `vid` = their rank from 0. Keys are dealt by range and written; ids are a task's offset plus a row's
    place in it. What the driver sees is one count per task."""
    placed = cut(keys.repartitionByRange(*by).sortWithinPartitions(*by).select(*by, F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("place")))
    counts = sorted((r["part"], r["count"]) for r in placed.groupBy("part").count().collect())
    offsets, total = [], 0
    for part, n in counts:
        offsets.append((part, total))
        total += n
    if not offsets:
        return placed.select(*by, F.col("place").alias("vid"))
    table = placed.sparkSession.createDataFrame(offsets, "part int, start long")
    return placed.join(F.broadcast(table), "part").select(*by, (F.col("start") + F.col("place")).alias("vid"))


def _by_dictionary(pairs: DataFrame, kinds: tuple[str, str]) -> Tuples:
    """Tuples of (a, b) string keys of two kinds."""
    keys = pairs.select(F.lit(kinds[0]).alias("kind"), F.col("a").alias("key")).union(pairs.select(F.lit(kinds[1]).alias("kind"), F.col("b").alias("key"))).distinct()
    ids = cut(ranked(keys, "kind", "key"))
    left = ids.where(F.col("kind") == kinds[0]).select(F.col("key").alias("a"), F.col("vid").alias("u"))
    right = ids.where(F.col("kind") == kinds[1]).select(F.col("key").alias("b"), F.col("vid").alias("v"))
    return Tuples(pairs.join(left, "a").join(right, "b").select("u", "v"), ids.count())


def _dictionary_sql(pairs: str, kinds: tuple[str, str]) -> tuple[str, str]:
    ids = f"SELECT kind, key, row_number() OVER (ORDER BY kind, key) - 1 AS vid FROM (SELECT '{kinds[0]}' AS kind, a AS key FROM ({pairs}) UNION SELECT '{kinds[1]}', b FROM ({pairs}))"
    return (
        f"SELECT x.vid AS u, y.vid AS v FROM ({pairs}) q JOIN ({ids}) x ON x.kind = '{kinds[0]}' AND x.key = q.a JOIN ({ids}) y ON y.kind = '{kinds[1]}' AND y.key = q.b",
        f"(SELECT count(*) FROM ({ids}))",
    )


def links(spark, sf_dir):
    df = load(spark, sf_dir, "pages", "page_id", "html")
    pairs = df.select(F.col("page_id").cast("string").alias("b"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("a")).where("a <> ''")
    return _by_dictionary(pairs.select("a", "b"), ("href", "page"))


_LINKS_SQL = _dictionary_sql("""SELECT a, b FROM (SELECT unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS a, CAST(page_id AS VARCHAR) AS b FROM pages) WHERE a <> ''""", ("href", "page"))


def doc_line(spark, sf_dir):
    df = load(spark, sf_dir, "documents", "doc_id", "text")
    pairs = df.select(F.col("doc_id").cast("string").alias("a"), F.explode(F.split("text", "\n")).alias("b")).where("b <> ''")
    return _by_dictionary(pairs, ("doc", "line"))


_DOC_LINE_SQL = _dictionary_sql("SELECT a, b FROM (SELECT CAST(doc_id AS VARCHAR) AS a, unnest(string_split(text, chr(10))) AS b FROM documents) WHERE b <> ''", ("doc", "line"))


def turns(spark, sf_dir):
    df = load(spark, sf_dir, "conversations", "conv_id", "turn")
    key = lambda c, t: F.concat(c.cast("string"), F.lit(":"), t.cast("string"))
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    rows = df.withColumn("after", after).where("after is not null")
    return _by_dictionary(rows.select(key(F.col("conv_id"), F.col("turn")).alias("a"), key(F.col("conv_id"), F.col("after")).alias("b")), ("turn", "turn"))


_TURNS_SQL = _dictionary_sql("SELECT conv_id || ':' || turn AS a, conv_id || ':' || after AS b FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM conversations) WHERE after IS NOT NULL", ("turn", "turn"))


def bench_doc(spark, sf_dir):
    items = load(spark, sf_dir, "benchmark", "item_id", "text").select(F.col("item_id").cast("string").alias("a"), F.explode(F.split("text", "\n")).alias("line")).where("line <> ''")
    docs = load(spark, sf_dir, "documents", "doc_id", "text").select(F.col("doc_id").cast("string").alias("b"), F.explode(F.split("text", "\n")).alias("line"))
    return _by_dictionary(items.join(docs, "line").select("a", "b").distinct(), ("item", "page"))


_BENCH_SQL = _dictionary_sql(
    "SELECT DISTINCT i.a, d.b FROM (SELECT CAST(item_id AS VARCHAR) AS a, unnest(string_split(text, chr(10))) AS line FROM benchmark) i JOIN (SELECT CAST(doc_id AS VARCHAR) AS b, unnest(string_split(text, chr(10))) AS line FROM documents) d ON i.line = d.line WHERE i.line <> ''", ("item", "page")
)

def knn(spark, sf_dir):
    from ..operators.relational import nearest

    found = cut(nearest(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), 5))
    return Tuples(_pair(found, F.col("a"), F.col("b")), size(spark, sf_dir, "embeddings"))


_KNN_SQL = """SELECT a AS u, b AS v FROM (SELECT p.vec_id AS a, w.vec_id AS b, row_number() OVER (PARTITION BY p.vec_id ORDER BY list_cosine_similarity(p.embedding::DOUBLE[], w.embedding::DOUBLE[]) DESC, w.vec_id) AS k FROM embeddings p JOIN embeddings w ON p.vec_id <> w.vec_id) z WHERE k <= 5"""

def status_priority(spark, sf_dir):
    df = load(spark, sf_dir, "orders", "o_orderpriority", "o_orderstatus")
    pairs = df.select(F.col("o_orderpriority").alias("a"), F.col("o_orderstatus").alias("b")).where("a is not null and b is not null").distinct()
    return _by_dictionary(pairs, ("priority", "status"))


_STATUS_SQL = _dictionary_sql("SELECT DISTINCT o_orderpriority AS a, o_orderstatus AS b FROM orders WHERE o_orderpriority IS NOT NULL AND o_orderstatus IS NOT NULL", ("priority", "status"))

#: The eight-vertex example, fixed.
TOY = ((0, 2), (0, 3), (0, 5), (1, 6), (1, 7), (2, 4), (3, 5), (3, 6), (4, 7), (5, 7))


def toy8(spark, sf_dir=None):
    return Tuples(spark.createDataFrame(TOY, "u long, v long"), 8)


def kron(scale: int):
    def build(spark, sf_dir=None):
        return Tuples(kronecker_edges(spark, scale), 1 << scale)

    return build


KRON_SCALE = 10
_USERS = "(SELECT max(user_id) + 1 FROM events)"

GRAPHS: dict[str, Graph] = {
    g.name: g
    for g in (
        Graph("toy8", toy8, "SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM (VALUES " + ", ".join(f"({u}, {v})" for u, v in TOY) + ") t(u, v)", "8", depth=6),
        Graph("order_part", order_part, f"SELECT l_orderkey AS u, l_partkey + {_n('orders')} AS v FROM lineitem", _n("orders", "part"), p=8, depth=11),
        Graph("part_supplier", part_supplier, f"SELECT l_partkey AS u, l_suppkey + {_n('part')} AS v FROM lineitem", _n("part", "supplier"), depth=7),
        Graph("customer_supplier", customer_supplier, f"SELECT o_custkey AS u, l_suppkey + {_n('customer')} AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey", _n("customer", "supplier"), depth=7),
        Graph("customer_part", customer_part, f"SELECT o_custkey AS u, l_partkey + {_n('customer')} AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey", _n("customer", "part"), depth=8),
        Graph(
            "star",
            star,
            _STAR_SQL
            + f"""UNION ALL SELECT o_custkey + {_n("region", "nation", "supplier")}, o_orderkey + {_n("region", "nation", "supplier", "customer", "part")} FROM orders
UNION ALL SELECT l_orderkey + {_n("region", "nation", "supplier", "customer", "part")}, l_partkey + {_n("region", "nation", "supplier", "customer")} FROM lineitem
UNION ALL SELECT l_partkey + {_n("region", "nation", "supplier", "customer")}, l_suppkey + {_n("region", "nation")} FROM lineitem""",
            _n("region", "nation", "supplier", "customer", "part", "orders"),
            p=8,
            depth=10,
        ),
        Graph("hierarchy", hierarchy, _STAR_SQL, _n("region", "nation", "supplier", "customer"), depth=6),
        Graph("order_customer", order_customer, f"SELECT o_orderkey AS u, o_custkey + {_n('orders')} AS v FROM orders", _n("orders", "customer"), _n("orders"), depth=4),
        Graph("event_chain", event_chain, "SELECT event_id AS u, v FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS v FROM events) WHERE v IS NOT NULL", _n("events"), directed=True, depth=0),
        Graph(
            "user_hour",
            user_hour,
            f"SELECT user_id AS u, dense_rank() OVER (ORDER BY date_trunc('hour', ts)) - 1 + {_USERS} AS v FROM events",
            f"({_USERS} + (SELECT count(DISTINCT date_trunc('hour', ts)) FROM events))",
            _USERS,
            depth=9,
        ),
        Graph("user_key", user_key, f"SELECT user_id AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) + {_USERS} AS v FROM events", f"({_USERS} + (SELECT max(CAST(json_extract_string(props, '$.k') AS BIGINT)) + 1 FROM events))", _USERS, depth=8),
        Graph("links", links, *_LINKS_SQL, depth=18),
        Graph("doc_line", doc_line, *_DOC_LINE_SQL, depth=24),
        Graph("knn", knn, _KNN_SQL, _n("embeddings"), depth=10),
        Graph("turns", turns, *_TURNS_SQL, directed=True, depth=12),
        Graph("bench_doc", bench_doc, *_BENCH_SQL, depth=6),
        Graph("kron", kron(KRON_SCALE), kronecker_sql(KRON_SCALE), str(1 << KRON_SCALE), p=8, depth=8),
    )
}


#: The graphs that every measure is registered for.
NAMED = tuple(GRAPHS)
#: Scales of the sweep at a fixed number of blocks, and (scale, blocks) of the ladder at a fixed block size.
SWEEP, LADDER = (8, 10, 12, 14), ((8, 2), (10, 8), (12, 32))
for _scale in {*SWEEP, *(k for k, _ in LADDER)}:
    GRAPHS[f"kron{_scale}"] = Graph(f"kron{_scale}", kron(_scale), kronecker_sql(_scale), str(1 << _scale), p=8, depth=9)

#: A graph as small as the example (five priorities, three statuses), from a given table.
GRAPHS["status_priority"] = Graph("status_priority", status_priority, *_STATUS_SQL, depth=6)


def derive(spark: SparkSession, sf_dir: str, name: str) -> Tuples:
    return GRAPHS[name].build(spark, sf_dir)
