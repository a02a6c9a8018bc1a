"""Quality by a language model: interpolated modified Kneser-Ney over five-character windows, trained on trusted text.

Counts, continuation counts, discounts and back-off weights are tables with one row per language and gram; nothing of the model is
collected. Texts are dealt into blocks of one language and bounded size. Each block states once which grams it needs, these
requests are joined with the model's shards, and the answers meet the block's texts again, where every text's perplexity is worked
out. A text is kept if its perplexity is at most a quantile of what held-back trusted texts of its language show.

Characters are taken as they stand, runs of white space as one blank; those from U+0C00 on share 1,024 codes. Null, empty and blank
texts have no perplexity and aren't kept. A null language is `und`. A language without trusted text has no model: perplexity null,
kept. Without held-back texts the quantile is taken over all trusted ones. Repeated rows are scored one by one; a label that occurs
twice for an id counts once, trusted only if all say so.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import TASK_ROWS, arrow_map, cut, small_batches, texts_of

ORDER, BITS = 5, 12
#: Bytes of text in a block, about.
BLOCK_BYTES = 40 << 20
BROADCAST_IDS = 500_000
#: Rows of grams in a file of a written table, about.
FILE_ROWS = 100_000
_BASE = 1.0 / (1 << BITS)
#: Characters of a language with codes of their own.
LETTERS = (1 << BITS) - 256
#: Bounds of the length classes, in characters, and held-back texts that a class needs.
LENGTHS, LEAST = (250, 500, 1_000, 2_000, 4_000), 60
#: Held-back texts of a language from which its quantile stands by itself, and what is added to it where there are fewer, since so few
#: don't show so high a quantile.
FIRM, MARGIN = 100, 0.1


def alphabets(trusted: DataFrame, lang: str = "lang", text: str = "text") -> dict[str, np.ndarray]:
    """By language, its characters in code order and their codes: the commonest LETTERS, counted over all trusted texts."""

    def make():
        def run(batch):
            names, texts = batch.column(0).to_pylist(), texts_of(batch.column(1))
            out = [[], [], []]
            for name in sorted(set(names)):
                codes = np.frombuffer("".join([t for t, x in zip(texts, names, strict=True) if x == name]).encode("utf-32-le", "surrogatepass"), np.uint32)
                found, n = np.unique(codes, return_counts=True)
                for column, values in zip(out, ([name] * len(found), found.tolist(), n.tolist()), strict=True):
                    column += values
            return pa.RecordBatch.from_arrays([pa.array(out[0], pa.string()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int64())], ["lang", "code", "n"])

        return run

    counts = arrow_map(trusted.select(lang, text), "lang string, code long, n long", make).groupBy("lang", "code").agg(F.sum("n").alias("n"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "code"))  # of at most 1,114,112 characters
    found: dict[str, list] = {}
    for r in counts.withColumn("place", place).where(F.col("place") <= LETTERS).collect():
        found.setdefault(r["lang"], []).append((r["code"], r["place"]))
    return {k: np.array(sorted(v), dtype=np.int64).T for k, v in found.items()}


def coded(codes: np.ndarray, alphabet: np.ndarray | None) -> np.ndarray:
    """Codes of up to BITS bits; 0 stays 0."""
    codes = codes.astype(np.int64)
    shared = LETTERS + 1 + codes % 255
    if alphabet is None:
        return np.where(codes < LETTERS, codes, shared)
    at = np.minimum(np.searchsorted(alphabet[0], codes), len(alphabet[0]) - 1)
    return np.where(codes == 0, 0, np.where(alphabet[0][at] == codes, alphabet[1][at], shared))


def grams(texts: list[str], alphabet: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """ORDER-character windows, one for every character of a text, and where each text's begin. Texts are led by code 0."""
    plain = [" ".join(t.split()) for t in texts]
    lead = "\0" * (ORDER - 1)
    codes = np.frombuffer("".join([lead + t for t in plain]).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    if len(codes):
        most = int(codes.max())
        if most < 1 << 16:  # a table is faster than a search
            codes = coded(np.arange(most + 1), alphabet)[codes]
        else:
            codes = coded(codes, alphabet)
    codes = codes.astype(np.int64)
    key = codes.copy()
    for j in range(1, ORDER):
        key[j:] |= codes[:-j] << (BITS * j)
    sizes = np.array([len(t) for t in plain], dtype=np.int64)
    ends = np.cumsum(sizes + ORDER - 1)
    skip = np.zeros(len(codes), dtype=bool)
    for j in range(ORDER - 1):
        skip[ends - sizes - 1 - j] = True
    return key[~skip], np.concatenate(([0], np.cumsum(sizes)))


class Table:
    """Grams to numbers, for lookups of long arrays: one slot per hash, and a sorted overflow for grams whose slot is taken."""

    def __init__(self):
        self.keys = np.zeros(0, dtype=np.int64)
        self.values = np.zeros(0)
        self._build()

    def _build(self) -> None:
        self.shift = np.uint64(64 - max(10, int(4 * len(self.keys) + 1).bit_length()))
        self.slot_keys = np.full(1 << (64 - int(self.shift)), -1, dtype=np.int64)
        self.slot_at = np.zeros(len(self.slot_keys), dtype=np.int64)
        slot = self._slot(self.keys)
        self.slot_keys[slot] = self.keys
        self.slot_at[slot] = np.arange(len(self.keys))
        over = np.flatnonzero(self.slot_keys[slot] != self.keys)
        over = over[np.argsort(self.keys[over])]
        self.over_keys, self.over_at = self.keys[over], over

    def _slot(self, g: np.ndarray) -> np.ndarray:
        return ((g.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).view(np.int64)

    def find(self, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where each gram's number stands, and which grams are missing (as positions)."""
        slot = self._slot(g)
        at = self.slot_at[slot]
        miss = np.flatnonzero(self.slot_keys[slot] != g)
        if len(miss) and len(self.over_keys):
            rest = g[miss]
            spot = np.minimum(np.searchsorted(self.over_keys, rest), len(self.over_keys) - 1)
            found = self.over_keys[spot] == rest
            at[miss[found]] = self.over_at[spot[found]]
            miss = miss[~found]
        return at, miss

    def add(self, keys: np.ndarray, values: np.ndarray | None = None) -> None:
        self.keys = np.concatenate((self.keys, keys))
        self.values = np.concatenate((self.values, np.zeros(len(keys)) if values is None else values))
        self._build()

    def learn(self, g: np.ndarray) -> None:
        miss = self.find(g)[1]
        if len(miss):
            self.add(np.unique(g[miss]))


def tagged(k: int, gram: np.ndarray) -> np.ndarray:
    """A gram's key: its length above its characters."""
    return gram & ((1 << (BITS * k)) - 1) | (k << 60)


def needed(full: np.ndarray) -> np.ndarray:
    """Keys of all grams and contexts that the probability of these windows' last characters depends on."""
    parts = [np.zeros(1, dtype=np.int64)]
    for k in range(ORDER, 0, -1):
        full = np.unique(full & ((1 << (BITS * k)) - 1))
        parts.append(tagged(k, full))
        if k > 1:
            parts.append(tagged(k - 1, np.unique(full >> BITS)))
    return np.unique(np.concatenate(parts))


def _find(keys: np.ndarray, of: np.ndarray, values: np.ndarray, default: float) -> np.ndarray:
    if not len(keys):
        return np.full(len(of), default)
    at = np.minimum(np.searchsorted(keys, of), len(keys) - 1)
    return np.where(keys[at] == of, values[at], default)


def log2_probabilities(full: np.ndarray, keys: np.ndarray, share: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Of each window's last character given those before it; keys in order with their discounted shares and back-off weights."""
    p = np.full(len(full), _BASE)
    for k in range(1, ORDER + 1):
        context = tagged(k - 1, full >> BITS) if k > 1 else np.zeros(len(full), dtype=np.int64)
        p = _find(keys, tagged(k, full), share, 0.0) + _find(keys, context, weight, 1.0) * p
    return np.log2(p)


def _bundle(batches):
    """Rows (id, lang, text, part) as (lang, part, packed): the rows of a batch that go to one block, in one compressed piece."""
    options = pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", compression_level=4))
    for batch in batches:
        blocks = batch.select(["lang", "part"]).to_pandas().groupby(["lang", "part"], sort=False).indices
        for (lang, part), at in blocks.items():
            sink = pa.BufferOutputStream()
            piece = batch.take(pa.array(at))
            with pa.ipc.new_stream(sink, piece.schema, options=options) as stream:
                stream.write_batch(piece)
            yield pa.RecordBatch.from_arrays([pa.array([lang], pa.string()), pa.array([part], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["lang", "part", "packed"])


def _unbundle(packed: pa.Scalar) -> pa.Table:
    return pa.ipc.open_stream(packed.as_buffer()).read_all()


def count_grams(docs: DataFrame, lang: str = "lang", text: str = "text", letters: dict[str, np.ndarray] | None = None) -> DataFrame:
    """(lang, g, c): how often each window occurs in each language. letters: the languages' alphabets."""
    shared = docs.sparkSession.sparkContext.broadcast(letters or {})  # at most LETTERS pairs a language

    def run(batches):
        held: dict[str, list] = {}
        size = 0

        def flush():
            for name, parts in held.items():
                g, c = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
                g, back = np.unique(g, return_inverse=True)
                c = np.bincount(back, weights=c).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(g), pa.string()), pa.array(g), pa.array(c)], ["lang", "g", "c"])
            held.clear()

        for batch in batches:
            names, texts = batch.column(0).to_pylist(), texts_of(batch.column(1))
            for name in sorted(set(names)):
                mine = [t for t, x in zip(texts, names, strict=True) if x == name]
                for i in range(0, len(mine), 400):
                    found = np.unique(grams(mine[i : i + 400], shared.value.get(name))[0], return_counts=True)
                    held.setdefault(name, []).append(found)
                    size += len(found[0])
                if size > 1_000_000:
                    yield from flush()
                    size = 0
        yield from flush()

    return docs.select(lang, text).mapInArrow(run, "lang string, g long, c long").groupBy("lang", "g").agg(F.sum("c").alias("c"))


def model(counts: DataFrame, docs: int) -> DataFrame:
    """(lang, key, share, weight) of every gram and context of all lengths. docs: how many texts were counted, for the number of files."""
    counts = cut(counts, 50 * docs, FILE_ROWS)
    level = counts.select(F.lit(ORDER).alias("k"), "lang", "g", "c")
    levels = []
    for k in range(ORDER - 1, 0, -1):
        level = level.groupBy("lang", F.col("g").bitwiseAND(F.lit((1 << (BITS * k)) - 1)).alias("g")).agg(F.count("*").alias("c")).select(F.lit(k).alias("k"), "lang", "g", "c")
        levels.append(level)
    lower = levels[0]
    for x in levels[1:]:
        lower = lower.unionByName(x)
    rows = counts.select(F.lit(ORDER).alias("k"), "lang", "g", "c").unionByName(cut(lower, counts.count(), FILE_ROWS))
    found: dict[tuple, dict] = {}
    for r in rows.where("c <= 4").groupBy("lang", "k", "c").count().collect():
        found.setdefault((r["lang"], r["k"]), {})[r["c"]] = r["count"]
    pairs = [(r["lang"], r["k"]) for r in rows.select("lang", "k").distinct().collect()]
    table = []
    for lang, k in pairs:
        n = [found.get((lang, k), {}).get(i, 0) for i in range(1, 5)]
        y = n[0] / (n[0] + 2 * n[1]) if n[0] + n[1] else 0.5
        discounts = [(i + 1) - (i + 2) * y * n[i + 1] / n[i] if n[i] and n[i + 1] else 0.5 * (i + 1) for i in range(3)]
        table.append((lang, k, *[min(max(d, 0.05), i + 0.95) for i, d in enumerate(discounts)]))
    if not table:
        return counts.sparkSession.createDataFrame([], "lang string, key long, share float, weight float")
    by = F.broadcast(counts.sparkSession.createDataFrame(table, "lang string, k int, d1 double, d2 double, d3 double"))  # five rows a language
    rows = rows.join(by, ["lang", "k"]).select("k", "lang", "g", "c", F.when(F.col("c") == 1, F.col("d1")).when(F.col("c") == 2, F.col("d2")).otherwise(F.col("d3")).alias("d"), F.shiftright("g", BITS).alias("h"))
    context = Window.partitionBy("lang", "k", "h")
    rows = rows.withColumns({"total": F.sum("c").over(context), "weight": F.sum("d").over(context) / F.sum("c").over(context), "nth": F.row_number().over(context.orderBy("g"))})
    key = lambda k, g: F.shiftleft(k.cast("long"), 60).bitwiseOR(g)
    share = F.struct(key(F.col("k"), F.col("g")).alias("key"), ((F.col("c") - F.col("d")) / F.col("total")).alias("share"), F.lit(None).cast("double").alias("weight"))
    weight = F.struct(key(F.col("k") - 1, F.col("h")).alias("key"), F.lit(None).cast("double").alias("share"), F.col("weight"))
    parts = rows.select("lang", F.explode(F.when(F.col("nth") == 1, F.array(share, weight)).otherwise(F.array(share))).alias("x")).select("lang", "x.*")
    return parts.groupBy("lang", "key").agg(F.coalesce(F.max("share"), F.lit(0.0)).cast("float").alias("share"), F.coalesce(F.max("weight"), F.lit(1.0)).cast("float").alias("weight"))


def perplexities(docs: DataFrame, table: DataFrame, id_column: str = "doc_id", text: str = "text", lang: str = "lang", letters: dict[str, np.ndarray] | None = None) -> DataFrame:
    """(id, lang, n_chars, perplexity) of every row. letters: as the model's counts were made with."""
    shared = docs.sparkSession.sparkContext.broadcast(letters or {})
    kind = dict(docs.dtypes)[id_column]
    name = F.coalesce(F.col(lang), F.lit("und"))
    sizes = {r[0]: r[1] for r in docs.groupBy(name.alias("l")).agg(F.sum(F.octet_length(text)).alias("n")).collect()}
    many = F.create_map(*[x for k, n in sizes.items() for x in (F.lit(k), F.lit(max(1, -(-(n or 0) // BLOCK_BYTES))))]) if sizes else F.create_map(F.lit("und"), F.lit(1))
    blocks = max(1, sum(max(1, -(-(n or 0) // BLOCK_BYTES)) for n in sizes.values()))
    dealt = docs.select(F.col(id_column), name.alias("lang"), F.col(text).alias("text"), F.pmod(F.xxhash64(F.col(id_column).cast("string")), many[name]).alias("part"))
    # the one shuffle of texts, which both uses below read; a task's texts of a block travel together, compressed
    dealt = dealt.mapInArrow(_bundle, "lang string, part long, packed binary").repartition(min(4 * blocks, max(blocks, 2_000)), "lang", "part")

    def ask(batches):
        held: dict[tuple, Table] = {}
        for batch in batches:
            for n, p, packed in zip(*(batch.column(i) for i in range(3)), strict=True):
                seen = held.setdefault((n.as_py(), p.as_py()), Table())
                mine = texts_of(_unbundle(packed).column(2))
                for i in range(0, len(mine), 200):
                    seen.learn(grams(mine[i : i + 200], shared.value.get(n.as_py()))[0])
        for (n, p), seen in held.items():
            keys = needed(np.sort(seen.keys))
            for i in range(0, len(keys), 100_000):
                some = keys[i : i + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array([n] * len(some), pa.string()), pa.array(np.full(len(some), p, dtype=np.int64)), pa.array(some)], ["lang", "part", "key"])

    requests = dealt.mapInArrow(ask, "lang string, part long, key long")
    answers = requests.join(table, ["lang", "key"]).select("lang", "part", "key", "share", "weight")

    def score(docs: pa.Table, answers: pa.Table) -> pa.Table:
        keys = answers.column("key").to_numpy()
        order = np.argsort(keys)
        keys, share, weight = keys[order], answers.column("share").to_numpy()[order].astype(np.float64), answers.column("weight").to_numpy()[order].astype(np.float64)
        known, out = Table(), []
        for packed in docs.column("packed"):
            table = _unbundle(packed)
            n_all, value_all = [], []
            for i in range(0, table.num_rows, 200):
                g, at = grams(texts_of(table.column(2).slice(i, 200)), shared.value.get(table.column(1)[0].as_py()))
                n = np.diff(at)
                sums = np.zeros(len(n))
                if len(g) and len(keys):
                    spot, miss = known.find(g)
                    if len(miss):
                        fresh = np.unique(g[miss])
                        known.add(fresh, log2_probabilities(fresh, keys, share, weight))
                        spot = known.find(g)[0]
                    sums[n > 0] = np.add.reduceat(known.values[spot], at[:-1][n > 0])
                n_all.append(n)
                value_all.append(np.exp2(-sums / np.maximum(n, 1)))
            n, value = np.concatenate(n_all), np.concatenate(value_all)
            out.append(pa.Table.from_arrays([table.column(0), table.column(1), pa.array(n), pa.array(value, mask=(n == 0) | (len(keys) == 0))], [id_column, "lang", "n_chars", "perplexity"]))
        return pa.concat_tables(out) if out else pa.table({id_column: [], "lang": [], "n_chars": [], "perplexity": []})

    return dealt.groupBy("lang", "part").cogroup(answers.groupBy("lang", "part")).applyInArrow(score, f"{id_column} {kind}, lang string, n_chars long, perplexity double")


def held_back(id_column: str):
    """An eighth of the trusted texts, by a hash of the id, is kept from the counts and sets the limits."""
    return F.pmod(F.xxhash64(F.col(id_column).cast("string"), F.lit("held back")), F.lit(8)) == 0


def length_class(n_chars):
    return sum([(n_chars >= x).cast("int") for x in LENGTHS], F.lit(0))


def limits(scored: DataFrame, trusted: DataFrame, quantile: float, id_column: str = "doc_id") -> DataFrame:
    """(lang, length, highest) for every length class of every language that has trusted texts; a few rows a language."""
    own = scored.join(trusted, id_column, "left_semi").where("perplexity is not null").withColumn("length", length_class(F.col("n_chars")))
    back = F.when(held_back(id_column), F.col("perplexity"))
    at = lambda x: F.percentile_approx(x, quantile, 100_000)
    firm = lambda x: at(x) * F.when(F.count(x) >= FIRM, F.lit(1.0)).otherwise(F.lit(1 + MARGIN))
    whole = own.groupBy("lang").agg(F.coalesce(firm(back), firm(F.col("perplexity"))).alias("whole"))
    parts = own.groupBy("lang", "length").agg(F.when(F.count(back) >= LEAST, at(back)).alias("part"))
    every = whole.select("lang", "whole", F.explode(F.sequence(F.lit(0), F.lit(len(LENGTHS)))).alias("length"))
    return every.join(parts, ["lang", "length"], "left").select("lang", "length", F.coalesce("part", "whole").alias("highest"))


def classify(docs: DataFrame, labels: DataFrame, quantile: float = 0.99, id_column: str = "doc_id", text: str = "text", lang: str = "lang", quality: str = "quality") -> DataFrame:
    """(id, lang, n_chars, perplexity, highest, kept) of every row; `highest` is the quantile of the held-back trusted texts of its
    language and length class."""
    marks = cut(labels.groupBy(id_column).agg(F.min(quality).alias("q")).where("q = 1").select(id_column), labels.count())
    ids = F.broadcast(marks) if marks.count() <= BROADCAST_IDS else marks
    name = F.coalesce(F.col(lang), F.lit("und")).alias("lang")
    trusted = docs.join(ids, id_column, "left_semi").where(~held_back(id_column) & F.col(text).isNotNull()).select(name, F.col(text).alias("text"))
    small_batches(docs.sparkSession)
    letters = alphabets(trusted)
    counts = count_grams(trusted, letters=letters)
    n = docs.count()
    table = model(counts, n)
    files = max(1, -(-n // TASK_ROWS))
    scored = cut(perplexities(docs, table, id_column, text, lang, letters).repartition(files))  # a few numbers a row
    bounds = cut(limits(scored, ids, quantile, id_column).coalesce(1))
    bounds = F.broadcast(bounds) if bounds.count() <= BROADCAST_IDS else bounds
    kept = F.when(F.col("n_chars") == 0, F.lit(False)).otherwise(F.coalesce(F.col("perplexity") <= F.col("highest"), F.lit(True)))
    scored = scored.withColumn("length", length_class(F.col("n_chars"))).join(bounds, ["lang", "length"], "left")
    return scored.select(id_column, "lang", "n_chars", "perplexity", "highest", kept.alias("kept"))
