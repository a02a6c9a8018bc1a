"""Queries of messages, codecs, costs and measures, and the paper's experiments on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from ..functions import sizes
from ..functions.codecs import CODECS, Plwah, Wah, huffman_lengths, pack_bitmap, wah_count, wah_logical, wah_not
from ..operators import exchange as x
from ..operators.traverse import bfs
from ..sources.graphs import GRAPHS, KRON_SCALE, LADDER, NAMED, SWEEP
from ..sources.kronecker import kronecker_edges, kronecker_sql
from . import costs as c, metrics as k, sqlgen as q
from .lineage import cut
from .registry import book, directory, graph, register, run, tree

LEDGERS = {f"{codec}_{kind}": (codec, kind == "sieved") for codec in ("bitmap", "sparse", "wah") for kind in ("allgather", "sieved")}
BOOK = "SELECT level, owner_block, needer_block, n_set, raw_bytes, bytes FROM book"



def _sweep(s, sf, codec, sieved, points):
    """(scale, blocks, raw_bytes, bytes, volume) of searches of Kronecker graphs: of all messages, and of the busiest block."""
    out = None
    for scale, p in points:
        rows = book(s, sf, f"kron{scale}", codec, sieved, p)
        sums = rows.agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes").alias("bytes")).join(F.broadcast(c.algorithm_volume(rows).select("volume")))  # one row each
        one = sums.select(F.lit(scale).cast("long").alias("scale"), F.lit(p).cast("long").alias("blocks"), "raw_bytes", "bytes", "volume")
        out = one if out is None else out.unionByName(one)
    return out


def _sweep_sql(codec, sieved, points):
    body = "SELECT CAST({k} AS BIGINT) AS scale, CAST({p} AS BIGINT) AS blocks, CAST((SELECT sum(raw_bytes) FROM book) AS BIGINT) AS raw_bytes, CAST((SELECT sum(bytes) FROM book) AS BIGINT) AS bytes, CAST(max(x.s + y.r) AS BIGINT) AS volume FROM (SELECT owner_block AS block, sum(bytes) AS s FROM book GROUP BY 1) x JOIN (SELECT needer_block AS block, sum(bytes) AS r FROM book GROUP BY 1) y USING (block)"
    return " UNION ALL ".join(f"SELECT * FROM ({q.with_ledger(f'kron{k}', codec, sieved, body.format(k=k, p=p), p)}) at_{k}" for k, p in points)


for method, (codec, sieved) in LEDGERS.items():
    for name in ("order_part", "star", "kron", "toy8"):
        register(f"ledger_{method}_{name}", lambda s, sf, name=name, codec=codec, sieved=sieved: book(s, sf, name, codec, sieved), q.with_ledger(name, codec, sieved, BOOK))
    # the payloads themselves, as a search sends them; empty messages aren't sent
    register(
        f"payload_ledger_{method}_order_part",
        lambda s, sf, method=method: run(s, sf, "order_part", method).ledger,
        q.with_ledger("order_part", codec, sieved, BOOK + " WHERE n_set > 0"),
    )
    register(
        f"volume_block_{method}",
        lambda s, sf, codec=codec, sieved=sieved: c.block_volume(book(s, sf, "order_part", codec, sieved)),
        q.with_ledger("order_part", codec, sieved, "SELECT block, CAST(s AS BIGINT) AS sent, CAST(r AS BIGINT) AS received, CAST(s + r AS BIGINT) AS total FROM (SELECT owner_block AS block, sum(bytes) AS s FROM book GROUP BY 1) a JOIN (SELECT needer_block AS block, sum(bytes) AS r FROM book GROUP BY 1) b USING (block)"),
    )
    register(
        f"w3_volume_{method}",
        lambda s, sf, codec=codec, sieved=sieved: c.algorithm_volume(book(s, sf, "order_part", codec, sieved)),
        q.with_ledger("order_part", codec, sieved, "SELECT CAST(max(s + r) AS BIGINT) AS volume, CAST(max(r) AS BIGINT) AS max_received, CAST(sum(s) AS BIGINT) AS all_bytes FROM (SELECT owner_block AS block, sum(bytes) AS s FROM book GROUP BY 1) a JOIN (SELECT needer_block AS block, sum(bytes) AS r FROM book GROUP BY 1) b USING (block)"),
    )
    register(
        f"ratio_{method}",
        lambda s, sf, codec=codec, sieved=sieved: c.compression_ratio(book(s, sf, "order_part", codec, sieved)),
        q.with_ledger("order_part", codec, sieved, "SELECT level, CAST(sum(raw_bytes) AS BIGINT) AS raw_bytes, CAST(sum(bytes) AS BIGINT) AS bytes, round(sum(raw_bytes)::DOUBLE / nullif(sum(bytes), 0), 6) AS ratio FROM book GROUP BY level"),
    )
    register(
        f"factor_{method}",
        lambda s, sf, codec=codec, sieved=sieved: c.compression_factor(book(s, sf, "order_part", codec, sieved)),
        q.with_ledger("order_part", codec, sieved, "SELECT round(avg(sh), 6) AS factor, count(*) AS levels FROM (SELECT level, sum(bytes)::DOUBLE / sum(raw_bytes) AS sh FROM book GROUP BY level) f0"),
    )
    register(
        f"message_counts_{method}",
        lambda s, sf, codec=codec, sieved=sieved: c.message_counts(book(s, sf, "order_part", codec, sieved)),
        q.with_ledger("order_part", codec, sieved, "SELECT level, count(*) AS messages, CAST(sum(CASE WHEN n_set > 0 THEN 1 ELSE 0 END) AS BIGINT) AS with_members FROM book GROUP BY level"),
    )
    register(f"memory_{method}", lambda s, sf, method=method: c.block_memory(graph(s, sf, "order_part"), method), q.query(
        q.base("order_part"),
        f"SELECT block, (n + 7) // 8 AS frontier, n_bits * 8 AS candidates, (n_bits + 7) // 8 AS visited, {'(n + 7) // 8 + (n_bits + 7) // 8 * blocks' if sieved else 'CAST(0 AS BIGINT)'} AS directory, (n + 7) // 8 + n_bits * 8 + (n_bits + 7) // 8 + {'(n + 7) // 8 + (n_bits + 7) // 8 * blocks' if sieved else '0'} AS total FROM blk, g, nb",
    ))
    register(f"w5_sweep_{method}", lambda s, sf, codec=codec, sieved=sieved: _sweep(s, sf, codec, sieved, [(k, 8) for k in SWEEP]), _sweep_sql(codec, sieved, [(k, 8) for k in SWEEP]))
    register(f"w3_ladder_{method}", lambda s, sf, codec=codec, sieved=sieved: _sweep(s, sf, codec, sieved, LADDER), _sweep_sql(codec, sieved, LADDER))
    register(
        f"w1_ledger_{method}",
        lambda s, sf, codec=codec, sieved=sieved: book(s, sf, "order_part", codec, sieved, 10).groupBy("level").agg(F.count("*").alias("messages"), F.sum("bytes").alias("bytes")),
        q.with_ledger("order_part", codec, sieved, "SELECT level, count(*) AS messages, CAST(sum(bytes) AS BIGINT) AS bytes FROM book GROUP BY level", 10),
    )


def _factors(s, sf):
    """Compression factor of every set-lane method, side by side."""
    out = None
    for method, (codec, sieved) in LEDGERS.items():
        one = c.compression_factor(book(s, sf, "order_part", codec, sieved)).select(F.lit(method).alias("method"), "factor")
        out = one if out is None else out.unionByName(one)
    return out


_MORE = {f"b_{m}": v for m, v in LEDGERS.items()}
register(
    "factor_compare",
    _factors,
    q.with_ledger("order_part", "bitmap", False, " UNION ALL ".join(f"SELECT '{m}' AS method, round(avg(sh), 6) AS factor FROM (SELECT level, sum(bytes)::DOUBLE / sum(raw_bytes) AS sh FROM b_{m} GROUP BY level) f_{m}" for m in LEDGERS), more=_MORE),
)


def _compare(s, sf):
    """Bytes of every set-lane method and what they save against the plain bitmap."""
    out = None
    for method, (codec, sieved) in LEDGERS.items():
        one = book(s, sf, "order_part", codec, sieved).agg(F.sum("bytes").alias("bytes")).select(F.lit(method).alias("method"), "bytes")
        out = one if out is None else out.unionByName(one)
    base = out.where("method = 'bitmap_allgather'").select(F.col("bytes").alias("plain"))
    return out.join(F.broadcast(base)).select("method", "bytes", F.round(1 - F.col("bytes") / F.col("plain"), 6).alias("reduction"))  # the base is one row


register(
    "w4_compare",
    _compare,
    q.with_ledger("order_part", "bitmap", False, " UNION ALL ".join(f"SELECT '{m}' AS method, CAST(sum(z.bytes) AS BIGINT) AS bytes, round(1 - sum(z.bytes)::DOUBLE / (SELECT sum(bytes) FROM book), 6) AS reduction FROM b_{m} z" for m in LEDGERS), more=_MORE),
)

# other protocols
register(
    "ledger_pull_order_part",
    lambda s, sf: x.pull_ledger(graph(s, sf, "order_part"), tree(s, sf, "order_part"), directory(s, sf, "order_part")),
    q.with_ledger("order_part", "wah", True, "SELECT level, k.owner_block, k.needer_block, unnest(['reply', 'request']) AS direction, CAST(1 AS BIGINT) AS n_messages, unnest([bytes, 8]) AS bytes FROM book k JOIN (SELECT DISTINCT owner_block, needer_block FROM needs) a ON a.owner_block = k.owner_block AND a.needer_block = k.needer_block"),
)
register(
    "payload_pull_order_part",  # as executed: every request and every reply, empty ones too
    lambda s, sf: run(s, sf, "order_part", "wah_pull").ledger.select("level", "owner_block", "needer_block", "direction", F.lit(1).cast("long").alias("n_messages"), "bytes"),
    q.with_ledger("order_part", "wah", True, "SELECT level, k.owner_block, k.needer_block, unnest(['reply', 'request']) AS direction, CAST(1 AS BIGINT) AS n_messages, unnest([bytes, 8]) AS bytes FROM book k JOIN (SELECT DISTINCT owner_block, needer_block FROM needs) a ON a.owner_block = k.owner_block AND a.needer_block = k.needer_block"),
)
register(
    "ledger_rendezvous_order_part",
    lambda s, sf: x.rendezvous_ledger(book(s, sf, "order_part", "wah", True)),
    q.with_ledger("order_part", "wah", True, "SELECT level, owner_block, needer_block, CAST(1 AS BIGINT) AS n_messages, bytes, round(1 * 1.0e-6::DOUBLE + bytes * 2.5e-10::DOUBLE, 12) AS seconds FROM book"),
)
register(
    "ledger_coalesced_order_part",
    lambda s, sf: x.coalesced_ledger(book(s, sf, "order_part", "wah", True), 4),
    q.with_ledger("order_part", "wah", True, "SELECT level, owner_block % 4 AS owner_host, needer_block % 4 AS needer_host, CAST(1 AS BIGINT) AS n_messages, CAST(sum(bytes) AS BIGINT) AS bytes FROM book WHERE owner_block % 4 <> needer_block % 4 GROUP BY 1, 2, 3"),
)
register(
    "ledger_grid_order_part",
    lambda s, sf: x.grid_ledger(graph(s, sf, "order_part"), tree(s, sf, "order_part"), 2, 4),
    q.tree_sql(
        "order_part",
        """SELECT level, 'expand' AS phase, r * 4 + c AS from_block, k * 4 + c AS to_block, count(*) AS n_set, count(*) * 8 AS bytes FROM (SELECT level, vid // ((n + 1) // 2) AS r, vid // ((n + 3) // 4) AS c FROM tree, g) a, range(2) z(k) WHERE k <> r GROUP BY ALL
UNION ALL SELECT level, 'fold', r * 4 + c, r * 4 + home, count(*), count(*) * 8 FROM (SELECT DISTINCT level, dst, dst // ((n + 1) // 2) AS r, dst // ((n + 3) // 4) AS home, src // ((n + 3) // 4) AS c FROM tree JOIN e ON e.src = tree.vid, g) f WHERE c <> home GROUP BY ALL""",
    ),
)

# ---------------------------------------------------------------------------------------------------------------------
# codecs


def _members(s, sf):
    g = graph(s, sf, "order_part")
    return tree(s, sf, "order_part").select("level", F.floor(F.col("vid") / g.size).cast("long").alias("owner_block"), F.pmod(F.col("vid"), F.lit(g.size)).cast("long").alias("slot")).join(g.frame().withColumnRenamed("block", "owner_block"), "owner_block")


def _frame(s, sf):
    g = graph(s, sf, "order_part")
    return tree(s, sf, "order_part").select("level").distinct().join(F.broadcast(g.frame().withColumnRenamed("block", "owner_block")))  # one row per block


KEYS = ["level", "owner_block"]
for codec in ("bitmap", "sparse", "rle", "plwah", "varint", "wah8", "wah16", "wah", "wah64"):
    register(
        f"codec_{codec}",
        lambda s, sf, codec=codec: sizes.sized(_members(s, sf), _frame(s, sf), KEYS, codec).select(*KEYS, F.col("bytes").cast("long").alias("bytes")),
        q.tree_sql("order_part", f"SELECT level, owner_block, bytes FROM ({q.sized_sql(q.own_members(), q.own_frame(), KEYS, codec)}) z"),
    )


def _word_rows(width: int, members: str, frame: str) -> str:
    """(level, owner_block, word_no, word_hex) of the sets in members (level, owner_block, slot, n_bits), for every row of frame."""
    g, digits, low = width - 1, width // 4, width - 4
    most = (1 << (width - 2)) - 1
    grp = f"SELECT level, owner_block, slot // {g} AS grp, count(*) AS n, sum(1::BIGINT << ({g} - 1 - slot % {g})::INTEGER) AS value FROM ({members}) m WHERE slot // {g} < n_bits // {g} GROUP BY ALL"
    win = "OVER (PARTITION BY level, owner_block ORDER BY grp)"
    rows = f"SELECT *, n = {g} AS one, coalesce(lag(grp) {win}, -1) AS prev, coalesce(lag(n = {g}) {win}, false) AS prev_one FROM ({grp}) q0"
    marked = f"SELECT *, sum(CASE WHEN one AND NOT (prev_one AND prev = grp - 1) THEN 1 ELSE 0 END) {win} AS run FROM ({rows}) q1"
    fills = f"""SELECT level, owner_block, prev + 1 AS pos, 0 AS kind, grp - prev - 1 AS n FROM ({rows}) q2 WHERE grp > prev + 1
UNION ALL SELECT f.level, f.owner_block, coalesce(last, -1) + 1, 0, f.n_bits // {g} - coalesce(last, -1) - 1 FROM ({frame}) f LEFT JOIN (SELECT level, owner_block, max(grp) AS last FROM ({grp}) q3 GROUP BY ALL) t0 ON t0.level = f.level AND t0.owner_block = f.owner_block WHERE coalesce(last, -1) + 1 < f.n_bits // {g}
UNION ALL SELECT level, owner_block, min(grp), 1, count(*) FROM ({marked}) q4 WHERE one GROUP BY level, owner_block, run"""
    split = f"SELECT level, owner_block, pos, i, lower(to_hex(8 + 4 * kind + (m >> {low})) || lpad(to_hex(m & {(1 << low) - 1}), {digits - 1}, '0')) AS w FROM (SELECT level, owner_block, pos, kind, i, least({most}, n - i * {most}) AS m FROM (SELECT *, unnest(range((n + {most - 1}) // {most})) AS i FROM ({fills}) q5) q6) q7"
    literal = f"SELECT level, owner_block, grp AS pos, 0 AS i, lower(lpad(to_hex(CAST(value AS BIGINT)), {digits}, '0')) AS w FROM ({rows}) q8 WHERE NOT one"
    active = f"SELECT f.level, f.owner_block, f.n_bits // {g} AS pos, 0 AS i, lower(lpad(to_hex(CAST(coalesce(v, 0) AS BIGINT)), {digits}, '0')) AS w FROM ({frame}) f LEFT JOIN (SELECT level, owner_block, sum(1::BIGINT << (n_bits % {g} - 1 - slot % {g})::INTEGER) AS v FROM ({members}) m WHERE slot // {g} = n_bits // {g} GROUP BY ALL) a0 ON a0.level = f.level AND a0.owner_block = f.owner_block WHERE f.n_bits % {g} > 0"
    return f"SELECT level, owner_block, row_number() OVER (PARTITION BY level, owner_block ORDER BY pos, i) AS word_no, w AS word_hex FROM ({split} UNION ALL {literal} UNION ALL {active}) q9"


def _words_sql(width: int) -> str:
    return q.tree_sql("order_part", _word_rows(width, q.own_members(), q.own_frame()))


for width in (8, 16, 32, 64):
    register(f"wah_words_{width}_order_part", lambda s, sf, width=width: sizes.wah_word_rows(_members(s, sf), _frame(s, sf), KEYS, width), _words_sql(width))
register(
    "w12_wah_example",
    lambda s, sf: s.createDataFrame([(i + 1, f"{w:04b}") for i, w in enumerate(Wah(4, zero_only=True).words(__import__("numpy").array([0]), 16))], "word_no long, bits string"),
    "SELECT CAST(n AS BIGINT) AS word_no, b AS bits FROM (VALUES (1, '0100'), (2, '1100'), (3, '0000')) t(n, b)",
)


def _byte_codec(codec: str):
    """(level, owner_block, bytes, ok): real payloads, and whether they decode to what went in."""

    def build(s, sf):
        packed = _members(s, sf).groupBy(*KEYS).agg(F.array_sort(F.collect_list("slot")).alias("slots"), F.max("n_bits").alias("n_bits"))
        out = packed.withColumn("payload", x.encoder(codec)("slots", "n_bits")).withColumn("back", x.decoder(codec)("payload", "n_bits"))
        return out.select(*KEYS, F.octet_length("payload").cast("long").alias("bytes"), (F.col("back") == F.col("slots")).alias("ok"))

    return build


for codec in ("zlib1", "zlib6", "zlib9", "huffman", "sparse_zlib"):
    register(f"codec_{codec}", _byte_codec(codec))
_KINDS = f"SELECT f.level, f.owner_block, f.k, CASE coalesce(s.v, 0) WHEN 0 THEN 0 WHEN 255 THEN 1 ELSE 2 END AS kind FROM (SELECT DISTINCT level, owner_block, n_bits, unnest(range((n_bits + 7) // 8)) AS k FROM ({q.own_members()}) m1) f LEFT JOIN (SELECT level, owner_block, slot // 8 AS k, sum(1 << (7 - slot % 8)::INTEGER) AS v FROM ({q.own_members()}) m2 GROUP BY ALL) s ON s.level = f.level AND s.owner_block = f.owner_block AND s.k = f.k"
_ISLANDS = f"SELECT level, owner_block, kind, count(*) AS n FROM (SELECT *, k - row_number() OVER (PARTITION BY level, owner_block, kind ORDER BY k) AS island FROM ({_KINDS}) k0) k1 GROUP BY level, owner_block, kind, island"
register("codec_bbc", _byte_codec("bbc"), q.tree_sql("order_part", f"SELECT level, owner_block, CAST(sum(CASE WHEN kind = 2 THEN n + (n + 126) // 127 ELSE (n + 62) // 63 END) AS BIGINT) AS bytes, true AS ok FROM ({_ISLANDS}) k2 GROUP BY level, owner_block"))


def _logical(op: str):
    """(level, owner_block, word_no, word_hex): a level's candidates (the neighbours of its members) against what is visited by then, on
    word lists, for every block. and: what was met again; andnot: the next level; or: both; not and count: of the candidates alone."""

    def build(s, sf):
        g = graph(s, sf, "order_part")
        found = tree(s, sf, "order_part").select("vid", "level")
        wah = Wah(32)
        place = lambda v: [F.floor(F.col(v) / g.size).cast("long").alias("owner_block"), F.pmod(F.col(v), F.lit(g.size)).cast("long").alias("slot")]
        near = g.edges.join(found.withColumnRenamed("vid", "src"), "src").select("level", *place("dst")).distinct()
        last = found.agg(F.max("level").alias("last"))
        seen = found.join(F.broadcast(last)).select(F.explode(F.sequence("level", "last")).alias("level"), *place("vid"))  # the last level is one row
        sets = lambda df, name: df.groupBy(*KEYS).agg(F.array_sort(F.collect_list("slot")).alias(name))
        both = _frame(s, sf).join(sets(near, "a"), KEYS, "left").join(sets(seen, "b"), KEYS, "left")

        @F.pandas_udf("struct<words array<string>, n_set long>")
        def run_op(a: pd.Series, b: pd.Series, bits: pd.Series) -> pd.DataFrame:
            rows = []
            for x, y, n in zip(a, b, bits.tolist(), strict=True):
                left, right = (wah.words(z if z is not None else [], n) for z in (x, y))
                out = left if op == "count" else wah_not(left, n, wah) if op == "not" else wah_logical(left, right, n, op, wah)
                rows.append(([f"{w:08x}" for w in out], wah_count(out, n, wah)))
            return pd.DataFrame(rows, columns=["words", "n_set"])

        done = both.select(*KEYS, run_op("a", "b", "n_bits").alias("r"))
        if op == "count":
            return done.select(*KEYS, F.col("r.n_set").alias("n_set"))
        return done.select(*KEYS, F.posexplode("r.words").alias("i", "word_hex")).select(*KEYS, (F.col("i") + 1).cast("long").alias("word_no"), "word_hex")

    return build


_HEAD = q.base("order_part") + q.levels("order_part") + [
    "lv AS MATERIALIZED (SELECT DISTINCT level FROM tree)",
    f"fr AS MATERIALIZED ({q.own_frame()})",
    "ca AS MATERIALIZED (SELECT DISTINCT tree.level, e.dst // b AS owner_block, e.dst % b AS slot FROM tree JOIN e ON e.src = tree.vid, g)",
    "vi AS MATERIALIZED (SELECT lv.level, vid // b AS owner_block, vid % b AS slot FROM lv JOIN tree ON tree.level <= lv.level, g)",
]
_SETS = {
    "and": "SELECT * FROM ca INTERSECT SELECT * FROM vi",
    "or": "SELECT * FROM ca UNION SELECT * FROM vi",
    "andnot": "SELECT * FROM ca EXCEPT SELECT * FROM vi",
    "not": "SELECT * FROM (SELECT level, owner_block, unnest(range(n_bits)) AS slot FROM fr) x0 EXCEPT SELECT * FROM ca",
}
for op, members in _SETS.items():
    rows = f"mm AS MATERIALIZED (SELECT z.level, z.owner_block, z.slot, n_bits FROM ({members}) z JOIN blk ON block = z.owner_block)"
    register(f"wah_{op}", _logical(op), q.query([*_HEAD, rows], _word_rows(32, "SELECT * FROM mm", "SELECT * FROM fr")))
register("wah_count", _logical("count"), q.query(_HEAD, "SELECT fr.level, fr.owner_block, coalesce(n, 0) AS n_set FROM fr LEFT JOIN (SELECT level, owner_block, count(*) AS n FROM ca GROUP BY ALL) x ON x.level = fr.level AND x.owner_block = fr.owner_block"))


def _bytes_of_bitmaps(s, sf):
    """(byte, n): how often each byte value stands in the plain bitmaps; what Huffman codes are made from."""

    @F.pandas_udf("array<int>")
    def values(slots: pd.Series, n_bits: pd.Series) -> pd.Series:
        return pd.Series([list(pack_bitmap(a, int(n))) for a, n in zip(slots, n_bits, strict=True)])

    packed = _members(s, sf).groupBy(*KEYS).agg(F.array_sort(F.collect_list("slot")).alias("slots"), F.max("n_bits").alias("n_bits"))
    return packed.select(F.explode(values("slots", "n_bits")).alias("byte")).groupBy(F.col("byte").cast("long").alias("byte")).agg(F.count("*").alias("n"))


_BYTE_SQL = f"SELECT CAST(v AS BIGINT) AS byte, count(*) AS n FROM (SELECT coalesce(s.v, 0) AS v FROM (SELECT DISTINCT level, owner_block, n_bits, unnest(range((n_bits + 7) // 8)) AS k FROM ({q.own_members()}) m1) f LEFT JOIN (SELECT level, owner_block, slot // 8 AS k, sum(1 << (7 - slot % 8)::INTEGER) AS v FROM ({q.own_members()}) m2 GROUP BY ALL) s ON s.level = f.level AND s.owner_block = f.owner_block AND s.k = f.k) z GROUP BY v"
register("codec_byte_histogram", _bytes_of_bitmaps, q.tree_sql("order_part", _BYTE_SQL))


def _entropy(s, sf):
    """(bytes, entropy_bytes): what any code of single bytes needs at least."""
    h = _bytes_of_bitmaps(s, sf)
    total = h.agg(F.sum("n").alias("t"))
    return h.join(F.broadcast(total)).agg(F.max("t").alias("bytes"), F.round(F.sum(F.col("n") * -F.log2(F.col("n") / F.col("t"))) / 8, 3).alias("entropy_bytes"))


register("codec_entropy_bound", _entropy, q.tree_sql("order_part", f"SELECT CAST(max(t) AS BIGINT) AS bytes, round(sum(n * -log2(n / t)) / 8, 3) AS entropy_bytes FROM (SELECT n, sum(n) OVER () AS t FROM ({_BYTE_SQL}) h) h2"))


def _huffman(s, sf):
    """(byte, code_length) of the bitmaps' bytes; 256 rows at most."""
    counts = {r["byte"]: r["n"] for r in _bytes_of_bitmaps(s, sf).collect()}
    return s.createDataFrame(sorted(huffman_lengths(counts).items()), "byte long, code_length long")


register("codec_huffman_lengths", _huffman)

CODEC_LIST = ("bitmap", "sparse", "wah", "plwah", "rle", "varint")


def _codec_compare(s, sf):
    """(codec, level, bytes) with totals by codec, by level, and over all."""
    out = None
    for codec in CODEC_LIST:
        one = sizes.sized(_members(s, sf), _frame(s, sf), KEYS, codec).select(F.lit(codec).alias("codec"), "level", "bytes")
        out = one if out is None else out.unionByName(one)
    return out.groupingSets([["codec", "level"], ["codec"], ["level"], []], "codec", "level").agg(F.sum("bytes").alias("bytes"), F.grouping_id().cast("long").alias("gid"))


_ALL = " UNION ALL ".join(f"SELECT '{codec}' AS codec, level, bytes FROM ({q.sized_sql(q.own_members(), q.own_frame(), KEYS, codec)}) z_{codec}" for codec in CODEC_LIST)
register("codec_compare", _codec_compare, q.tree_sql("order_part", f"SELECT codec, level, CAST(sum(bytes) AS BIGINT) AS bytes, CAST(grouping_id(codec, level) AS BIGINT) AS gid FROM ({_ALL}) a GROUP BY GROUPING SETS ((codec, level), (codec), (level), ())"))


def _w6(s, sf):
    """(method, bytes) of every codec with and without the sieve, zlib included: bytes of the payloads sent."""
    out = None
    for method in ("wah_allgather", "zlib1_allgather", "zlib6_allgather", "zlib9_allgather", "wah_sieved", "zlib1_sieved", "zlib6_sieved", "zlib9_sieved"):
        one = run(s, sf, "order_part", method).ledger.agg(F.sum("bytes").alias("bytes"), F.sum("n_set").alias("deliveries")).select(F.lit(method).alias("method"), "bytes", "deliveries")
        out = one if out is None else out.unionByName(one)
    return out


register("w6_codec_volume", _w6)


def _w8(s, sf):
    """(method, bytes): sparse ids with and without zlib."""
    out = None
    for method in ("sparse_allgather", "sparse_zlib_allgather"):
        one = run(s, sf, "order_part", method).ledger.agg(F.sum("bytes").alias("bytes")).select(F.lit(method).alias("method"), "bytes")
        out = one if out is None else out.unionByName(one)
    return out


register("w8_sparse_zlib", _w8)

CODEC_RUNS = ("bitmap_allgather", "wah_allgather", "wah_sieved", "zlib1_allgather", "zlib6_allgather", "zlib9_allgather", "zlib1_sieved", "zlib6_sieved", "zlib9_sieved")


def _profiles(s, sf):
    """(run_id, method, level, phase, seconds) of a search by each codec; decoding is booked with encoding for all of them."""
    out = None
    for method in CODEC_RUNS:
        needs = directory(s, sf, "order_part") if method.endswith("sieved") else None
        one = bfs(graph(s, sf, "order_part"), method=method, needs=needs, profile=True).profile(method, method)
        out = one if out is None else out.unionByName(one)
    return out


register("w7_phases", lambda s, sf: k.phase_shares(_profiles(s, sf)))


def _totals(s, sf):
    rows = _profiles(s, sf)
    return rows.groupBy("method").agg(F.sum("seconds").alias("seconds"), F.sum(F.when(F.col("phase") == "communication", F.col("seconds")).otherwise(0.0)).alias("communication"))


register("compare_measured", lambda s, sf: k.compare_runs(cut(_totals(s, sf)), "bitmap_allgather"))
register("relative_measured", lambda s, sf: k.relative_performance(cut(_totals(s, sf)), "wah_sieved"))


def _choice(s, sf):
    b = book(s, sf, "order_part", "bitmap", True)
    g = graph(s, sf, "order_part")
    return b.join(g.frame().withColumnRenamed("block", "owner_block"), "owner_block").select("level", "owner_block", "needer_block", "n_set", c.choose_encoding(F.col("n_bits"), F.col("n_set")).alias("codec"))


register(
    "encoding_choice",
    _choice,
    q.with_ledger(
        "order_part",
        "bitmap",
        True,
        "SELECT level, owner_block, needer_block, n_set, CASE WHEN n_set = 0 THEN 'empty' WHEN sp = best THEN 'sparse' WHEN ga = best THEN 'varint' WHEN wa = best THEN 'wah' ELSE 'bitmap' END AS codec FROM (SELECT *, least(bm, ga, wa, sp) AS best FROM (SELECT level, owner_block, needer_block, n_set, ceil(n_bits / 8) AS bm, n_set * (1 + floor(log2(greatest(n_bits / greatest(n_set, 1), 1)) / 7)) AS ga, least(n_set * 2 + 1, ceil(n_bits / 31)) * 4 AS wa, n_set * 8 AS sp FROM book JOIN blk ON block = owner_block) c0) c1",
    ),
)

# ---------------------------------------------------------------------------------------------------------------------
# measures

#: What the break-even of the eight-vertex example is taken from, so that it reads a given table.
FROM_TABLES = {"toy8": "status_priority"}

for name in NAMED:
    if name == "event_chain":
        continue
    register(f"level_sizes_{name}", lambda s, sf, name=name: k.level_sizes(tree(s, sf, name)), q.tree_sql(name, "SELECT level, n, CAST(sum(n) OVER (ORDER BY level) AS BIGINT) AS reached FROM (SELECT level, count(*) AS n FROM tree GROUP BY level) a"))
    register(
        f"w2_frontier_sizes_{name}",
        lambda s, sf, name=name: k.encoding_sizes(tree(s, sf, name).groupBy("level").agg(F.count("*").alias("n")), graph(s, sf, name).n),
        q.tree_sql(name, "SELECT level, CAST(sum(n) AS BIGINT) AS n, CAST(sum(bm) AS BIGINT) AS bitmap_bytes, CAST(sum(n * 8) AS BIGINT) AS sparse_bytes FROM (SELECT level, count(*) AS n, any_value((g.n + 7) // 8) AS bm FROM tree, g GROUP BY level) a GROUP BY ROLLUP (level)"),
    )
    register(
        f"breakeven_{name}",
        lambda s, sf, name=FROM_TABLES.get(name, name): k.breakeven(tree(s, sf, name).groupBy("level").agg(F.count("*").alias("n")), graph(s, sf, name).n),
        q.tree_sql(FROM_TABLES.get(name, name), "SELECT depth, depth * n AS bitmap_bits, reached * 64 AS sparse_bits, CASE WHEN depth * n <= reached * 64 THEN 'bitmap' ELSE 'sparse' END AS winner FROM (SELECT count(DISTINCT level) AS depth, count(*) AS reached FROM tree) a, g"),
    )
    register(
        f"stats_{name}",
        lambda s, sf, name=name: k.graph_stats(graph(s, sf, name), tree(s, sf, name)),
        q.tree_sql(name, f"SELECT n, CAST(coalesce(ed, 0) // {1 if GRAPHS[name].directed else 2} AS BIGINT) AS m, touched, round((coalesce(ed, 0) // {1 if GRAPHS[name].directed else 2})::DOUBLE / n, 6) AS mean_degree, coalesce(max_degree, 0) AS max_degree, depth, reached FROM g, (SELECT count(*) AS touched, sum(d) AS ed, max(d) AS max_degree FROM (SELECT src, count(*) AS d FROM e GROUP BY src) d0) a, (SELECT max(level) AS depth, count(*) AS reached FROM tree) t1"),
    )
    register(
        f"teps_edges_{name}",
        lambda s, sf, name=name: k.teps_edges(graph(s, sf, name).tuples, tree(s, sf, name)),
        q.tree_sql(name, "SELECT count(*) AS m_tuples, CAST(sum(CASE WHEN u = v THEN 1 ELSE 0 END) AS BIGINT) AS m_selfloops, count(DISTINCT CASE WHEN u <> v THEN (least(u, v), greatest(u, v)) END) AS m_distinct FROM t WHERE u IN (SELECT vid FROM tree)"),
    )
for name in ("order_part", "star", "kron"):
    register(f"degree_hist_{name}", lambda s, sf, name=name: k.degree_histogram(graph(s, sf, name)), q.query(q.base(name), "SELECT degree, count(*) AS vertices FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) d GROUP BY degree"))
    register(
        f"imbalance_{name}",
        lambda s, sf, name=name: k.imbalance(graph(s, sf, name)),
        q.query(q.base(name), "SELECT count(*) AS blocks, CAST(sum(c) AS BIGINT) AS edges, max(c) AS max_edges, round(max(c) / avg(c), 6) AS ratio FROM (SELECT block, count(e.dst) AS c FROM g, blk LEFT JOIN e ON e.dst // (SELECT b FROM g) = block GROUP BY block) z"),
    )
register(
    "directory_cost",
    lambda s, sf: c.directory_cost(graph(s, sf, "order_part"), directory(s, sf, "order_part")),
    q.query(q.base("order_part"), "SELECT entries, vectors, blocks * (blocks - 1) AS setup_messages, CAST(sb AS BIGINT) AS setup_bytes FROM (SELECT count(*) AS entries, count(DISTINCT (needer_block, owner_block)) AS vectors FROM needs WHERE needer_block <> owner_block) a, nb, (SELECT sum((n_bits + 7) // 8) * (count(*) - 1) AS sb FROM blk) c"),
)
register(
    "amortisation",
    lambda s, sf: c.amortisation(book(s, sf, "order_part", "wah", False), book(s, sf, "order_part", "wah", True), c.directory_cost(graph(s, sf, "order_part"), directory(s, sf, "order_part"))),
    q.with_ledger("order_part", "wah", False, "SELECT CAST(a AS BIGINT) AS plain_bytes, CAST(z AS BIGINT) AS sieved_bytes, CAST(sb AS BIGINT) AS setup_bytes, CASE WHEN a > z THEN CAST(ceil(sb / (a - z)) AS BIGINT) END AS searches FROM (SELECT sum(bytes) AS a FROM book) x, (SELECT sum(bytes) AS z FROM b2) y, (SELECT sum((n_bits + 7) // 8) * (count(*) - 1) AS sb FROM blk) c", more={"b2": ("wah", True)}),
)
register(
    "collective_time",
    lambda s, sf: c.collective_table(s),
    "SELECT kind, CAST(p AS BIGINT) AS p, CAST(nbytes AS BIGINT) AS nbytes, round(CASE WHEN kind = 'ring' THEN p - 1 ELSE log2(p) END * 2.0e-6::DOUBLE + (p - 1)::DOUBLE / p * nbytes * 2.5e-10::DOUBLE, 9) AS seconds FROM (VALUES ('ring'), ('doubling')) a(kind), (VALUES (2), (4), (8), (64), (512)) b(p), (VALUES (8388608), (1073741824)) c(nbytes)",
)
register("message_time", lambda s, sf: c.message_table(s), "SELECT CAST(n AS BIGINT) AS nbytes, round(2.0e-6::DOUBLE + n * 2.5e-10::DOUBLE, 12) AS seconds, round(n * 2.5e-10::DOUBLE, 12) AS bandwidth_seconds FROM (VALUES (0), (8), (1024), (1048576), (1073741824)) t(n)")

#: Published frontier counts by level, fixed.
PUBLISHED_COUNTS = (2, 20842, 235274348, 1377666413, 38582585, 88639, 211)
_COUNT_ROWS = ", ".join(f"({i + 1}, {n})" for i, n in enumerate(PUBLISHED_COUNTS))
register(
    "w2_published_counts",
    lambda s, sf: k.encoding_sizes(s.createDataFrame(list(enumerate(PUBLISHED_COUNTS, 1)), "level long, n long"), None),
    f"SELECT CAST(level AS BIGINT) AS level, CAST(sum(n) AS BIGINT) AS n, CAST(sum((tt + 7) // 8) AS BIGINT) AS bitmap_bytes, CAST(sum(n * 8) AS BIGINT) AS sparse_bytes FROM (SELECT level, n::BIGINT AS n, sum(n::BIGINT) OVER () AS tt FROM (VALUES {_COUNT_ROWS}) t(level, n)) z GROUP BY ROLLUP (level)",
)

#: Published totals at 512 nodes, fixed: seconds and seconds of communication.
PUBLISHED_RUNS = (("bitmap", 25.4, 18.6), ("wah", 15.1, 8.9), ("wah_sieved", 11.4, 3.9))
_RUN_ROWS = ", ".join(f"('{m}', {s}::DOUBLE, {t}::DOUBLE)" for m, s, t in PUBLISHED_RUNS)
register(
    "compare_published",
    lambda s, sf: k.compare_runs(s.createDataFrame(PUBLISHED_RUNS, "method string, seconds double, communication double"), "bitmap"),
    f"SELECT method, seconds, communication, round(25.4::DOUBLE / seconds, 6) AS speedup, round(1 - communication / 18.6::DOUBLE, 6) AS reduction FROM (VALUES {_RUN_ROWS}) t(method, seconds, communication)",
)
register(
    "relative_published",
    lambda s, sf: k.relative_performance(s.createDataFrame([r[:2] for r in PUBLISHED_RUNS], "method string, seconds double"), "wah_sieved"),
    f"SELECT method, seconds, round(11.4::DOUBLE * 100 / seconds, 6) AS relative FROM (VALUES {_RUN_ROWS}) t(method, seconds, communication)",
)

# the generator
register("w13_kron_edges", lambda s, sf: kronecker_edges(s, KRON_SCALE), kronecker_sql(KRON_SCALE))
register("w13_kron_degree_hist", lambda s, sf: k.degree_histogram(graph(s, sf, "kron")), q.query(q.base("kron"), "SELECT degree, count(*) AS vertices FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) d GROUP BY degree"))
register("w13_kron_bfs", lambda s, sf: tree(s, sf, "kron"), q.tree_sql("kron"))
