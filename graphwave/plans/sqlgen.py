"""DuckDB texts of the oracles: trees by unrolled levels, directories, ledgers and code sizes by the shared formulas."""

from __future__ import annotations

from ..sources.graphs import GRAPHS


def base(name: str, p: int | None = None, source: str | None = None) -> list[str]:
    """CTEs: t tuples, e edges, g (n, p, b), blk (block, n_bits)."""
    x = GRAPHS[name]
    back = "" if x.directed else " UNION ALL SELECT v, u FROM t WHERE u <> v"
    p = p or x.p
    return [
        f"t AS MATERIALIZED (SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM ({x.tuples_sql}) q0)",
        f"e AS MATERIALIZED (SELECT DISTINCT src, dst FROM (SELECT u AS src, v AS dst FROM t WHERE u <> v{back}) q1)",
        f"g AS MATERIALIZED (SELECT n, CAST({p} AS BIGINT) AS p, (n + {p} - 1) // {p} AS b FROM (SELECT CAST({x.n_sql} AS BIGINT) AS n) q2)",
        f"blk AS MATERIALIZED (SELECT CAST(k AS BIGINT) AS block, least(b, n - k * b) AS n_bits FROM g, range({p}) r(k) WHERE n - k * b > 0)",
        "nb AS MATERIALIZED (SELECT count(*) AS blocks FROM blk)",
        "needs AS MATERIALIZED (SELECT DISTINCT dst // b AS needer_block, src // b AS owner_block, src % b AS slot FROM e, g)",
    ]


def levels(name: str, sources: list[str] | None = None, combine: str = "max", depth: int | None = None) -> list[str]:
    """CTEs up to tree(vid, level, parent)."""
    x = GRAPHS[name]
    depth = depth or x.depth
    sources = sources or [x.source_sql]
    seeds = " UNION ALL ".join(f"SELECT CAST({s} AS BIGINT) AS vid, CAST(0 AS BIGINT) AS level, CAST({s} AS BIGINT) AS parent" for s in sources)
    agg = {"max": "max(e.src)", "min": "min(e.src)"}[combine]
    out = [f"l0 AS MATERIALIZED ({seeds})", "s0 AS MATERIALIZED (SELECT vid, level, parent FROM l0)"]
    for k in range(1, depth + 1):
        out.append(f"l{k} AS MATERIALIZED (SELECT e.dst AS vid, CAST({k} AS BIGINT) AS level, {agg} AS parent FROM e JOIN l{k - 1} l ON e.src = l.vid WHERE NOT EXISTS (SELECT 1 FROM s{k - 1} s WHERE s.vid = e.dst) GROUP BY e.dst)")
        out.append(f"s{k} AS MATERIALIZED (SELECT * FROM s{k - 1} UNION ALL SELECT * FROM l{k})")
    out.append(f"tree AS MATERIALIZED (SELECT * FROM s{depth})")
    return out


def query(ctes: list[str], body: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n" + body


def tree_sql(name: str, body: str = "SELECT vid, level, parent FROM tree", **options) -> str:
    p = options.pop("p", None)
    return query(base(name, p) + levels(name, **options), body)


def chain_sql() -> str:
    """The event chain's tree in closed form: the events of the first event's user in order, from that event on."""
    return """WITH c AS (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events),
z AS (SELECT user_id, r FROM c WHERE event_id = 0)
SELECT CAST(c.event_id AS BIGINT) AS vid, CAST(c.r - z.r AS BIGINT) AS level, CAST(CASE WHEN c.r = z.r THEN c.event_id ELSE c.before END AS BIGINT) AS parent FROM c JOIN z ON c.user_id = z.user_id AND c.r >= z.r"""


def sized_sql(members: str, frame: str, keys: list[str], codec: str, words: bool = False) -> str:
    """(keys, n_bits, n_set, bytes); members has keys, slot, n_bits; frame has keys, n_bits."""
    k = ", ".join(keys)
    on = " AND ".join(f"f.{c} = x.{c}" for c in keys)
    fk = ", ".join(f"f.{c}" for c in keys)
    join = lambda sub, name: f"LEFT JOIN ({sub}) {name} ON " + " AND ".join(f"f.{c} = {name}.{c}" for c in keys)
    count = f"SELECT {k}, count(*) AS n_set FROM ({members}) m0 GROUP BY {k}"
    if codec == "bitmap":
        return f"SELECT {fk}, f.n_bits, coalesce(x.n_set, 0) AS n_set, (f.n_bits + 7) // 8 AS bytes FROM ({frame}) f LEFT JOIN ({count}) x ON {on}"
    if codec == "sparse":
        return f"SELECT {fk}, f.n_bits, coalesce(x.n_set, 0) AS n_set, coalesce(x.n_set, 0) * 8 AS bytes FROM ({frame}) f LEFT JOIN ({count}) x ON {on}"
    if codec == "varint":
        gap = f"SELECT {k}, slot - coalesce(lag(slot) OVER (PARTITION BY {k} ORDER BY slot), 0) AS gap FROM ({members}) m0"
        b = f"SELECT {k}, count(*) AS n_set, sum(CASE WHEN gap < 128 THEN 1 WHEN gap < 16384 THEN 2 WHEN gap < 2097152 THEN 3 WHEN gap < 268435456 THEN 4 ELSE 5 END) AS b FROM ({gap}) g0 GROUP BY {k}"
        return f"SELECT {fk}, f.n_bits, coalesce(x.n_set, 0) AS n_set, CAST(coalesce(x.b, 0) AS BIGINT) AS bytes FROM ({frame}) f LEFT JOIN ({b}) x ON {on}"
    if codec == "rle":
        new = f"SELECT {k}, slot, CASE WHEN slot - 1 = lag(slot) OVER (PARTITION BY {k} ORDER BY slot) THEN 0 ELSE 1 END AS fresh FROM ({members}) m0"
        b = f"SELECT {k}, count(*) AS n_set, sum(fresh) AS ones, max(slot) AS last FROM ({new}) g0 GROUP BY {k}"
        return f"SELECT {fk}, f.n_bits, coalesce(x.n_set, 0) AS n_set, CAST(4 * coalesce(2 * x.ones + CASE WHEN x.last < f.n_bits - 1 THEN 1 ELSE 0 END, 1) AS BIGINT) AS bytes FROM ({frame}) f LEFT JOIN ({b}) x ON {on}"
    width = {"wah": 32, "plwah": 32, "wah8": 8, "wah16": 16, "wah64": 64}[codec]
    g = width - 1
    most = (1 << 25) - 1 if codec == "plwah" else (1 << (width - 2)) - 1
    up = lambda x: f"(({x} + {most - 1}) // {most})"
    grp = f"SELECT {k}, slot // {g} AS grp, count(*) AS n FROM ({members}) m0 WHERE slot // {g} < n_bits // {g} GROUP BY {k}, slot // {g}"
    win = f"OVER (PARTITION BY {k} ORDER BY grp)"
    rows = f"SELECT {k}, grp, n, n = {g} AS one, grp - coalesce(lag(grp) {win}, -1) - 1 AS gap, coalesce(lag(n = {g}) {win}, false) AS prior FROM ({grp}) g1"
    marked = f"SELECT *, sum(CASE WHEN one AND NOT (prior AND gap = 0) THEN 1 ELSE 0 END) {win} AS run FROM ({rows}) g2"
    ones = f"SELECT {k}, sum(c) AS one_fills FROM (SELECT {k}, run, {up('count(*)')} AS c FROM ({marked}) g3 WHERE one GROUP BY {k}, run) g4 GROUP BY {k}"
    free = " AND NOT (n = 1 AND gap > 0)" if codec == "plwah" else ""
    sums = f"SELECT {k}, sum(CASE WHEN NOT one{free} THEN 1 ELSE 0 END) AS literals, sum({up('gap')}) AS zero_fills, max(grp) AS last FROM ({rows}) g5 GROUP BY {k}"
    total = f"coalesce(y.literals, 0) + coalesce(y.zero_fills, 0) + coalesce(z.one_fills, 0) + {up(f'(f.n_bits // {g} - 1 - coalesce(y.last, -1))')} + CASE WHEN f.n_bits % {g} > 0 THEN 1 ELSE 0 END"
    value = f"CAST({total} AS BIGINT) AS words" if words else f"CAST(({total}) * {width // 8} AS BIGINT) AS bytes"
    return f"SELECT {fk}, f.n_bits, coalesce(x.n_set, 0) AS n_set, {value} FROM ({frame}) f {join(count, 'x')} {join(sums, 'y')} {join(ones, 'z')}"


def own_members() -> str:
    return "SELECT tr.level, tr.vid // b AS owner_block, tr.vid % b AS slot, n_bits FROM tree tr, g, blk WHERE blk.block = tr.vid // b"


def own_frame() -> str:
    return "SELECT lv.level, blk.block AS owner_block, blk.n_bits FROM (SELECT DISTINCT level FROM tree) lv, blk"


def pair_members() -> str:
    return f"SELECT m.level, m.owner_block, d.needer_block, m.slot, m.n_bits FROM ({own_members()}) m JOIN needs d ON d.owner_block = m.owner_block AND d.slot = m.slot WHERE d.needer_block <> m.owner_block"


def pair_frame() -> str:
    return "SELECT lv.level, o.block AS owner_block, d.block AS needer_block, o.n_bits FROM (SELECT DISTINCT level FROM tree) lv, blk o, blk d WHERE o.block <> d.block"


def ledger_body(codec: str, sieved: bool) -> str:
    """(level, owner_block, needer_block, n_set, raw_bytes, bytes)."""
    if sieved:
        z = sized_sql(pair_members(), pair_frame(), ["level", "owner_block", "needer_block"], codec)
        return f"SELECT level, owner_block, needer_block, n_set, (n_bits + 7) // 8 AS raw_bytes, bytes FROM ({z}) z0"
    z = sized_sql(own_members(), own_frame(), ["level", "owner_block"], codec)
    return f"SELECT z0.level, z0.owner_block, d.block AS needer_block, z0.n_set, (z0.n_bits + 7) // 8 AS raw_bytes, z0.bytes FROM ({z}) z0, blk d WHERE d.block <> z0.owner_block"


def with_ledger(name: str, codec: str, sieved: bool, body: str, p: int | None = None, more: dict | None = None) -> str:
    """A query over book (the ledger) and any further ledgers by name."""
    ctes = base(name, p) + levels(name) + [f"book AS MATERIALIZED ({ledger_body(codec, sieved)})"]
    for other, (c, s) in (more or {}).items():
        ctes.append(f"{other} AS MATERIALIZED ({ledger_body(c, s)})")
    return query(ctes, body)
