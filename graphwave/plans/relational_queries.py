"""Queries of the plain relational operators that graphs are derived and read with."""

from __future__ import annotations

from math import isqrt

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import relational as r
from ..operators.layout import adjacency_lists
from ..sources.tables import load
from . import sqlgen as q
from .registry import graph, register, tree

L = lambda s, sf, name, *cols: load(s, sf, name, *cols)
E = lambda s, sf: graph(s, sf, "order_part").edges
B = q.base("order_part")
T = B + q.levels("order_part")

# scans, filters, projections
register("op_scan_pruned", lambda s, sf: L(s, sf, "lineitem", "l_orderkey", "l_partkey").where("l_partkey < 50"), "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_partkey < 50")
register("op_filter_between", lambda s, sf: L(s, sf, "orders", "o_orderkey", "o_orderdate").where("o_orderdate BETWEEN timestamp'1995-01-01' AND timestamp'1995-06-30'").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1995-06-30'")
register("op_filter_in_like", lambda s, sf: L(s, sf, "part", "p_partkey", "p_brand", "p_type").where("p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') OR p_type LIKE '%STEEL%'").select("p_partkey", "p_brand"), "SELECT p_partkey, p_brand FROM part WHERE p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') OR p_type LIKE '%STEEL%'")
register("op_filter_rlike", lambda s, sf: L(s, sf, "customer", "c_custkey", "c_name").where(F.col("c_name").rlike("[05]$")), "SELECT c_custkey, c_name FROM customer WHERE regexp_matches(c_name, '[05]$')")
register("op_filter_null_safe", lambda s, sf: graph(s, sf, "hierarchy").vertices().select("vid").join(tree(s, sf, "hierarchy"), "vid", "left").where(F.col("level").eqNullSafe(F.lit(None))).select("vid"), q.tree_sql("hierarchy", "SELECT CAST(i AS BIGINT) AS vid FROM range((SELECT n FROM g)) r(i) LEFT JOIN tree ON tree.vid = i WHERE tree.level IS NOT DISTINCT FROM NULL"))
register("op_filter_selfloops", lambda s, sf: graph(s, sf, "kron").tuples.where("u = v"), q.query(q.base("kron"), "SELECT u, v FROM t WHERE u = v"))
register("op_project_blocks", lambda s, sf: graph(s, sf, "order_part").blocked(), q.query(B, "SELECT src, dst, src // b AS src_block, src % b AS src_slot, dst // b AS dst_block, dst % b AS dst_slot FROM e, g"))
register("op_project_permuted", lambda s, sf: E(s, sf).select(F.pmod(F.col("src") * 7919 + 17, F.lit(graph(s, sf, "order_part").n)).alias("src"), F.pmod(F.col("dst") * 7919 + 17, F.lit(graph(s, sf, "order_part").n)).alias("dst")), q.query(B, "SELECT (src * 7919 + 17) % n AS src, (dst * 7919 + 17) % n AS dst FROM e, g"))
register("op_filter_subgraph", lambda s, sf: L(s, sf, "lineitem", "l_orderkey", "l_partkey", "l_shipdate").where("l_shipdate < timestamp'1997-01-01'").select("l_orderkey", "l_partkey").distinct(), "SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_shipdate < TIMESTAMP '1997-01-01'")
register("op_filter_labels", lambda s, sf: L(s, sf, "documents", "doc_id", "lang").join(L(s, sf, "labels", "doc_id", "quality").where("quality = 1").select("doc_id"), "doc_id", "left_semi"), "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")

# joins
#: Edges and the first two levels only: all that the joins below read.
T2 = B[:2] + q.levels("order_part", depth=2)
F1 = lambda s, sf: tree(s, sf, "order_part").where("level = 2").select(F.col("vid").alias("src"))
register("op_join_hash", lambda s, sf: E(s, sf).join(F1(s, sf).hint("shuffle_hash"), "src"), q.query(T2, "SELECT src, dst FROM e WHERE src IN (SELECT vid FROM l2)"))
register("op_join_merge", lambda s, sf: E(s, sf).join(F1(s, sf).hint("merge"), "src"), q.query(T2, "SELECT src, dst FROM e WHERE src IN (SELECT vid FROM l2)"))
register("op_join_broadcast", lambda s, sf: E(s, sf).join(F.broadcast(F1(s, sf)), "src"), q.query(T2, "SELECT src, dst FROM e WHERE src IN (SELECT vid FROM l2)"))
register("op_join_anti", lambda s, sf: E(s, sf).select("dst").distinct().join(F1(s, sf).withColumnRenamed("src", "dst"), "dst", "left_anti"), q.query(T, "SELECT DISTINCT dst FROM e WHERE dst NOT IN (SELECT vid FROM tree WHERE level = 2)"))
register("op_join_semi", lambda s, sf: graph(s, sf, "order_part").tuples.join(F1(s, sf).withColumnRenamed("src", "u"), "u", "left_semi"), q.query(T, "SELECT u, v FROM t WHERE u IN (SELECT vid FROM tree WHERE level = 2)"))
register("op_join_blocks", lambda s, sf: graph(s, sf, "order_part").frame().select(F.col("block").alias("owner")).join(F.broadcast(graph(s, sf, "order_part").frame().select(F.col("block").alias("needer")))), q.query(B, "SELECT o.block AS owner, d.block AS needer FROM blk o, blk d"))
DEGREES = lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("k")).groupBy("k").agg(F.count("*").alias("a"))
register("op_join_full", lambda s, sf: DEGREES(s, sf).join(tree(s, sf, "order_part").groupBy(F.col("level").alias("k")).agg(F.count("*").alias("b")), "k", "full_outer"), q.query(T, "SELECT coalesce(x.k, y.k) AS k, a, b FROM (SELECT k, count(*) AS a FROM (SELECT src, count(*) AS k FROM e GROUP BY src) x0 GROUP BY k) x FULL JOIN (SELECT level AS k, count(*) AS b FROM tree GROUP BY level) y ON x.k = y.k"))
register("op_join_left", lambda s, sf: graph(s, sf, "order_part").vertices().select("vid").join(tree(s, sf, "order_part").select("vid", "level"), "vid", "left"), q.query(T, "SELECT CAST(i AS BIGINT) AS vid, level FROM range((SELECT n FROM g)) r(i) LEFT JOIN tree ON vid = i"))


def _uneven(s, sf):
    """Ids in uneven blocks whose bounds are squares, as many as the graph's ids need."""
    bounds = s.range(isqrt(max(0, graph(s, sf, "order_part").n - 1)) + 1).select((F.col("id") * F.col("id")).alias("lo"), ((F.col("id") + 1) * (F.col("id") + 1)).alias("hi"), F.col("id").alias("block"))
    return r.range_join(tree(s, sf, "order_part").select("vid"), "vid", bounds, 256).select("vid", "block")


register("op_join_range", _uneven, q.query(T, "SELECT vid, CAST(k AS BIGINT) AS block FROM tree JOIN range((SELECT CAST(ceil(sqrt(n)) AS BIGINT) FROM g)) r(k) ON vid >= k * k AND vid < (k + 1) * (k + 1)"))
register("op_join_interval", lambda s, sf: r.interval_pairs(L(s, sf, "events", "event_id", "ts", "user_id"), "user_id", "ts", "event_id", 1800), "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts - x.ts <= INTERVAL 1800 SECOND AND (y.ts > x.ts OR (y.ts = x.ts AND y.event_id > x.event_id))")


def _as_of(s, sf):
    e = L(s, sf, "events", "event_id", "ts", "user_id", "event_type", "value")
    kind = e.groupBy("event_type").count().orderBy(F.desc("count"), "event_type").first()[0]
    left = e.where(F.col("event_type") != kind).select("event_id", "ts", "user_id")
    right = e.where(F.col("event_type") == kind).select("event_id", "ts", "user_id", F.col("event_id").alias("last_id"))
    return r.as_of(left, right, "user_id", "ts", "last_id", "event_id").select("event_id", "as_of")


register("op_join_as_of", _as_of, "WITH k AS (SELECT event_type FROM events GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 1), r AS (SELECT * FROM events WHERE event_type = (SELECT event_type FROM k)) SELECT l.event_id, (SELECT r.event_id FROM r WHERE r.user_id = l.user_id AND r.ts <= l.ts ORDER BY r.ts DESC, r.event_id DESC LIMIT 1) AS as_of FROM events l WHERE l.event_type <> (SELECT event_type FROM k)")


def _two_hop(s, sf):
    """Customers of one supplier's parts: A squared on the supplier side, counted by pair of suppliers."""
    e = graph(s, sf, "part_supplier").edges
    n = graph(s, sf, "part_supplier").n
    up = e.where("src < dst")
    both = up.select("src", F.col("dst").alias("a")).join(up.select("src", F.col("dst").alias("b")), "src").where("a < b")
    return both.groupBy("a", "b").agg(F.count("*").alias("parts"))


register("op_join_two_hop", _two_hop, q.query(q.base("part_supplier"), "SELECT x.dst AS a, y.dst AS b, count(*) AS parts FROM e x JOIN e y ON x.src = y.src AND x.src < x.dst AND y.src < y.dst AND x.dst < y.dst GROUP BY 1, 2"))
register("op_join_triangles", lambda s, sf: _triangles(graph(s, sf, "kron").edges), q.query(q.base("kron"), "SELECT count(*) AS triangles FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst WHERE x.src < x.dst AND y.src < y.dst"))


def _triangles(e):
    """Each triangle once: edges point from the smaller id on."""
    up = e.where("src < dst")
    wedge = up.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(up.select(F.col("src").alias("b"), F.col("dst").alias("c")), "b")
    return wedge.join(up.select(F.col("src").alias("a"), F.col("dst").alias("c")), ["a", "c"], "left_semi").agg(F.count("*").alias("triangles"))


register("op_join_salted", lambda s, sf: r.salted_join(graph(s, sf, "kron").edges, tree(s, sf, "kron").select(F.col("vid").alias("src"), "level"), "src", 8), q.query(q.base("kron") + q.levels("kron"), "SELECT src, dst, level FROM e JOIN tree ON vid = src"))
register("op_join_nearest", lambda s, sf: r.nearest(L(s, sf, "embeddings", "vec_id", "embedding"), 5).select("a", "b"), "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings), d AS (SELECT p.vec_id AS a, w.vec_id AS b, list_cosine_similarity(p.x, w.x) AS c FROM v p JOIN v w ON p.vec_id <> w.vec_id) SELECT a, b FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY c DESC, b) AS k FROM d) z WHERE k <= 5")

# aggregates
TR = lambda s, sf: tree(s, sf, "order_part")
register("op_agg_max_parent", lambda s, sf: E(s, sf).groupBy("dst").agg(F.max("src").alias("parent")), q.query(B, "SELECT dst, max(src) AS parent FROM e GROUP BY dst"))
register("op_agg_distinct", lambda s, sf: E(s, sf).agg(F.count_distinct("src").alias("n"), F.count("*").alias("m")), q.query(B, "SELECT count(DISTINCT src) AS n, count(*) AS m FROM e"))
register("op_agg_approx", lambda s, sf: E(s, sf).agg(F.count_distinct("src").alias("n"), F.approx_count_distinct("src", 0.02).alias("a")).select("n", (F.abs(F.col("a") - F.col("n")) <= 0.06 * F.col("n")).alias("within_three_errors")), q.query(B, "SELECT count(DISTINCT src) AS n, true AS within_three_errors FROM e"))
register("op_agg_bitmap", lambda s, sf: TR(s, sf).select("level", F.bitmap_bucket_number(F.col("vid") + 1).alias("bucket"), F.bitmap_bit_position(F.col("vid") + 1).alias("bit")).groupBy("level", "bucket").agg(F.bitmap_count(F.bitmap_construct_agg("bit")).alias("n")), q.query(T, "SELECT level, 1 + vid // 32768 AS bucket, count(*) AS n FROM tree GROUP BY ALL"))
register("op_agg_bitmap_or", lambda s, sf: TR(s, sf).select("level", F.bitmap_bucket_number(F.col("vid") + 1).alias("bucket"), F.bitmap_bit_position(F.col("vid") + 1).alias("bit")).groupBy("level", "bucket").agg(F.bitmap_construct_agg("bit").alias("b")).groupBy("bucket").agg(F.bitmap_count(F.bitmap_or_agg("b")).alias("n")), q.query(T, "SELECT 1 + vid // 32768 AS bucket, count(*) AS n FROM tree GROUP BY ALL"))
register("op_agg_bit_or", lambda s, sf: TR(s, sf).groupBy("level", F.floor(F.col("vid") / 31).cast("long").alias("grp")).agg(F.expr("bit_or(shiftleft(1L, cast(30 - vid % 31 as int)))").alias("word")), q.query(T, "SELECT level, vid // 31 AS grp, bit_or(1::BIGINT << (30 - vid % 31)::INTEGER) AS word FROM tree GROUP BY ALL"))
register("op_agg_rollup", lambda s, sf: TR(s, sf).withColumn("block", F.floor(F.col("vid") / 1000).cast("long")).rollup("level", "block").agg(F.count("*").alias("n")), q.query(T, "SELECT level, block, count(*) AS n FROM (SELECT level, vid // 1000 AS block FROM tree) z GROUP BY ROLLUP (level, block)"))
register("op_agg_cube", lambda s, sf: TR(s, sf).withColumn("half", F.col("vid") % 2).cube("level", "half").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("gid")), q.query(T, "SELECT level, half, count(*) AS n, CAST(grouping_id(level, half) AS BIGINT) AS gid FROM (SELECT level, vid % 2 AS half FROM tree) z GROUP BY CUBE (level, half)"))
register("op_agg_pivot", lambda s, sf: TR(s, sf).withColumn("half", F.col("vid") % 2).groupBy("level").pivot("half", [0, 1]).count().select("level", F.coalesce("0", F.lit(0)).alias("even"), F.coalesce("1", F.lit(0)).alias("odd")), q.query(T, "SELECT level, count(*) FILTER (vid % 2 = 0) AS even, count(*) FILTER (vid % 2 = 1) AS odd FROM tree GROUP BY level"))
register("op_agg_collect", lambda s, sf: E(s, sf).groupBy("src").agg(F.concat_ws(",", F.array_sort(F.collect_list("dst")).cast("array<string>")).alias("neighbours")), q.query(B, "SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS neighbours FROM e GROUP BY src"))
register("op_agg_percentile", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).agg(F.expr("percentile(d, 0.5)").alias("median"), F.expr("percentile(d, 0.99)").alias("p99")), q.query(B, "SELECT quantile_cont(d, 0.5) AS median, quantile_cont(d, 0.99) AS p99 FROM (SELECT src, count(*) AS d FROM e GROUP BY src) z"))
register("op_agg_max_by", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).groupBy((F.col("src") % 10).alias("k")).agg(F.max_by("src", F.struct("d", "src")).alias("hub"), F.max("d").alias("d")), q.query(B, "SELECT k, src AS hub, d FROM (SELECT src % 10 AS k, src, d, row_number() OVER (PARTITION BY src % 10 ORDER BY d DESC, src DESC) AS r FROM (SELECT src, count(*) AS d FROM e GROUP BY src) x) z WHERE r = 1"))
register("op_agg_having", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).where("d > 35"), q.query(B, "SELECT src, count(*) AS d FROM e GROUP BY src HAVING count(*) > 35"))
register("op_agg_harmonic", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).agg(F.round(F.count("*") / F.sum(1 / F.col("d")), 6).alias("mean")), q.query(B, "SELECT round(count(*) / sum(1.0::DOUBLE / d), 6) AS mean FROM (SELECT src, count(*) AS d FROM e GROUP BY src) z"))
register("op_agg_adjacency_lists", lambda s, sf: adjacency_lists(graph(s, sf, "order_part"), 16).select("dst_block", "src_block", "src_slot", F.col("chunk").cast("long").alias("chunk"), F.size("dst_slots").cast("long").alias("n")), q.query(B, "SELECT dst_block, src_block, src_slot, (r - 1) // 16 AS chunk, count(*) AS n FROM (SELECT dst // b AS dst_block, src // b AS src_block, src % b AS src_slot, row_number() OVER (PARTITION BY dst // b, src ORDER BY dst) AS r FROM e, g) z GROUP BY ALL"))

# windows
W = Window
DEG = lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d"))
D = "(SELECT src, count(*) AS d FROM e GROUP BY src)"
for fn in ("rank", "dense_rank"):
    register(f"op_window_{fn}", lambda s, sf, fn=fn: DEG(s, sf).select("src", getattr(F, fn)().over(W.partitionBy(F.col("src") % 7).orderBy("d")).cast("long").alias("r")), q.query(B, f"SELECT src, {fn}() OVER (PARTITION BY src % 7 ORDER BY d) AS r FROM {D} z"))
for fn in ("percent_rank", "cume_dist"):
    register(f"op_window_{fn}", lambda s, sf, fn=fn: DEG(s, sf).select("src", F.round(getattr(F, fn)().over(W.partitionBy(F.col("src") % 7).orderBy("d")), 9).alias("r")), q.query(B, f"SELECT src, round({fn}() OVER (PARTITION BY src % 7 ORDER BY d), 9) AS r FROM {D} z"))
register("op_window_ntile", lambda s, sf: DEG(s, sf).select("src", F.ntile(8).over(W.partitionBy(F.col("src") % 7).orderBy("d", "src")).cast("long").alias("r")), q.query(B, f"SELECT src, ntile(8) OVER (PARTITION BY src % 7 ORDER BY d, src) AS r FROM {D} z"))
register("op_window_lag_lead", lambda s, sf: DEG(s, sf).select("src", F.lag("src").over(W.partitionBy("d").orderBy("src")).alias("before"), F.lead("src").over(W.partitionBy("d").orderBy("src")).alias("after")), q.query(B, f"SELECT src, lag(src) OVER w AS before, lead(src) OVER w AS after FROM {D} z WINDOW w AS (PARTITION BY d ORDER BY src)"))
register("op_window_running", lambda s, sf: L(s, sf, "events", "event_id", "user_id", "ts").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM events")
register("op_window_range", lambda s, sf: L(s, sf, "events", "event_id", "user_id", "ts").withColumn("t", F.unix_seconds(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
register("op_window_first_last", lambda s, sf: L(s, sf, "events", "event_id", "user_id", "ts").select("user_id", F.first("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("a"), F.last("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("b")).distinct(), "SELECT DISTINCT user_id, first_value(event_id) OVER w AS a, last_value(event_id) OVER w AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")


def _islands(s, sf):
    v = TR(s, sf).where("level = 4").select("vid")
    k = v.withColumn("k", F.col("vid") - F.row_number().over(W.partitionBy(F.floor(F.col("vid") / 4096)).orderBy("vid")))
    return k.groupBy(F.floor(F.col("vid") / 4096).cast("long").alias("part"), "k").agg(F.min("vid").alias("start"), F.count("*").alias("n")).select("start", "n")


register("op_window_islands", _islands, q.query(T, "SELECT min(vid) AS start, count(*) AS n FROM (SELECT vid, vid // 4096 AS part, vid - row_number() OVER (PARTITION BY vid // 4096 ORDER BY vid) AS k FROM tree WHERE level = 4) z GROUP BY part, k"))

# sets, order, top
LV = lambda s, sf, k: TR(s, sf).where(F.col("level") == k).select("vid")
NB = lambda s, sf: E(s, sf).join(LV(s, sf, 2).withColumnRenamed("vid", "src"), "src").select(F.col("dst").alias("vid"))
NS = "SELECT dst AS vid FROM e JOIN tree ON src = vid WHERE level = 2"
LS = lambda k: f"SELECT vid FROM tree WHERE level = {k}"
register("op_set_union", lambda s, sf: LV(s, sf, 1).union(LV(s, sf, 2)).union(LV(s, sf, 3)), q.query(T, f"{LS(1)} UNION ALL {LS(2)} UNION ALL {LS(3)}"))
register("op_set_intersect", lambda s, sf: NB(s, sf).intersect(LV(s, sf, 3)), q.query(T, f"{NS} INTERSECT {LS(3)}"))
register("op_set_intersect_all", lambda s, sf: NB(s, sf).intersectAll(NB(s, sf)), q.query(T, f"{NS} INTERSECT ALL {NS}"))
register("op_set_except_all", lambda s, sf: NB(s, sf).exceptAll(LV(s, sf, 3)), q.query(T, f"{NS} EXCEPT ALL {LS(3)}"))
register("op_set_subtract", lambda s, sf: NB(s, sf).subtract(LV(s, sf, 1)), q.query(T, f"{NS} EXCEPT {LS(1)}"))
register("op_set_distinct", lambda s, sf: graph(s, sf, "kron").tuples.distinct(), q.query(q.base("kron"), "SELECT DISTINCT u, v FROM t"))
register("op_topk_hubs", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).orderBy(F.desc("d"), "src").limit(20), q.query(B, "SELECT src, count(*) AS d FROM e GROUP BY src ORDER BY d DESC, src LIMIT 20"))
register("op_topk_offset", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).orderBy(F.desc("d"), "src").offset(20).limit(20), q.query(B, "SELECT src, count(*) AS d FROM e GROUP BY src ORDER BY d DESC, src LIMIT 20 OFFSET 20"))
register("op_topk_per_group", lambda s, sf: E(s, sf).groupBy("src").agg(F.count("*").alias("d")).withColumn("r", F.row_number().over(W.partitionBy(F.col("src") % 5).orderBy(F.desc("d"), "src"))).where("r <= 3").select("src", "d"), q.query(B, "SELECT src, d FROM (SELECT *, row_number() OVER (PARTITION BY src % 5 ORDER BY d DESC, src) AS r FROM (SELECT src, count(*) AS d FROM e GROUP BY src) x) z WHERE r <= 3"))
register("op_sort_tree", lambda s, sf: TR(s, sf).orderBy("level", "vid"), q.query(T, "SELECT vid, level, parent FROM tree ORDER BY level, vid"))

# functions
register("op_fn_bits", lambda s, sf: TR(s, sf).select("vid", F.shiftleft("vid", 3).alias("l"), F.shiftright("vid", 2).alias("r"), F.col("vid").bitwiseAND(F.lit(255)).alias("a"), F.col("vid").bitwiseOR(F.lit(4096)).alias("o"), F.col("vid").bitwiseXOR(F.lit(77)).alias("x"), F.bit_count("vid").cast("long").alias("c"), F.bitwise_not("vid").alias("n")), q.query(T, "SELECT vid, vid << 3 AS l, vid >> 2 AS r, vid & 255 AS a, vid | 4096 AS o, xor(vid, 77) AS x, CAST(bit_count(vid) AS BIGINT) AS c, ~vid AS n FROM tree"))
register("op_fn_math", lambda s, sf: TR(s, sf).select("vid", F.least("vid", F.lit(100)).alias("lo"), F.greatest("vid", F.lit(100)).alias("hi"), F.round(F.log2(F.col("vid") + 1), 6).alias("lg"), F.pmod(F.col("vid") - 50, F.lit(7)).cast("long").alias("m"), F.ceil(F.col("vid") / 8).cast("long").alias("up")), q.query(T, "SELECT vid, least(vid, 100) AS lo, greatest(vid, 100) AS hi, round(log2(vid + 1), 6) AS lg, ((vid - 50) % 7 + 7) % 7 AS m, (vid + 7) // 8 AS up FROM tree"))
register("op_fn_hash", lambda s, sf: TR(s, sf).select("vid", F.md5(F.col("vid").cast("string").cast("binary")).alias("m"), F.sha2(F.col("vid").cast("string").cast("binary"), 256).alias("h")), q.query(T, "SELECT vid, md5(vid::VARCHAR) AS m, sha256(vid::VARCHAR) AS h FROM tree"))
register("op_fn_string", lambda s, sf: L(s, sf, "pages", "page_id", "url").select("page_id", F.lower("url").alias("u"), F.substring("url", 1, 12).alias("s"), F.regexp_extract("url", "//([^/]+)", 1).alias("host"), F.element_at(F.split("url", "/"), -1).alias("tail"), F.lpad(F.hex("page_id"), 8, "0").alias("h")), "SELECT page_id, lower(url) AS u, substring(url, 1, 12) AS s, regexp_extract(url, '//([^/]+)', 1) AS host, string_split(url, '/')[-1] AS tail, lpad(upper(to_hex(page_id)), 8, '0') AS h FROM pages")
register("op_fn_date", lambda s, sf: L(s, sf, "events", "event_id", "ts").select("event_id", F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm").alias("hour"), F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), F.datediff("ts", F.lit("2024-01-01")).cast("long").alias("days")), "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS hour, epoch_us(ts) AS us, datediff('day', DATE '2024-01-01', ts::DATE) AS days FROM events")
register("op_fn_array", lambda s, sf: s.range(1, 30).select(F.col("id").alias("k"), F.size(F.sequence(F.lit(1).cast("long"), F.col("id"))).cast("long").alias("n"), F.aggregate(F.transform(F.sequence(F.lit(1).cast("long"), F.col("id")), lambda x: x * x), F.lit(0).cast("long"), lambda a, x: a + x).alias("squares"), F.size(F.filter(F.sequence(F.lit(1).cast("long"), F.col("id")), lambda x: x % 3 == 0)).cast("long").alias("thirds")), "SELECT CAST(k AS BIGINT) AS k, CAST(k AS BIGINT) AS n, CAST(list_sum(list_transform(range(1, k + 1), lambda x: x * x)) AS BIGINT) AS squares, CAST(k // 3 AS BIGINT) AS thirds FROM range(1, 30) r(k)")
register("op_fn_json", lambda s, sf: L(s, sf, "events", "event_id", "props").select("event_id", F.from_json("props", "k long").getField("k").alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
register("op_fn_map", lambda s, sf: TR(s, sf).groupBy("level").agg(F.count("*").alias("n")).groupBy().agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("level", "n")))).alias("m")).select(F.explode("m").alias("level", "n")), q.query(T, "SELECT level, count(*) AS n FROM tree GROUP BY level"))
