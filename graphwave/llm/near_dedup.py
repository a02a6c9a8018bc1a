"""Near-duplicate classes by BagMinHash signatures, bands, and exact multiset overlap.

Words are lower-cased and blank-separated; a text is the multiset of its five-word shingles (a shorter text is one shingle), and two
texts are linked if the weighted Jaccard similarity of their multisets is at least 0.8. Classes are the connected components of the
links; a class is named by its smallest id.

1. Texts with the same words in the same order are one text; the smallest id stands for them.
2. A BagMinHash signature: every shingle has a Poisson process over its discretised weight, split into the ranges [0,1), [1,2), [2,4),
   [4,8), ...; a text of weight w takes all ranges below w and, of the range that w cuts, the points below w. Points fall into slots
   at random, and each slot keeps the lowest. Two slots agree with a probability equal to the weighted Jaccard similarity. Only
   points below the highest slot so far are drawn, so a text costs time in proportion to its shingles, plus a constant.
3. 24 bands of 5 slots: a pair at 0.8 shares a band with probability 0.99993.
4. Texts in a crowded band are dealt anew, without loss: with its elements (shingle, occurrence) in order of rarity, a text must share
   one of its first n - ceil(0.8 n) + 1 with every text it is linked to. Each such element with another holder is a bucket.
5. Buckets are never paired out. In rounds, the most central members of each bucket (most elements shared with others) are compared,
   exactly, with members of other classes; links merge classes at once, so a group of copies costs one comparison per member. Rounds
   take ever more members, until no bucket holds members of two classes that haven't been compared. Nothing is dropped or capped.

All tables stay distributed and each step's result is written to the shared checkpoint folder. Texts without words are never
duplicates: each is its own class. Null texts count as such. A repeated row has one row per repetition in the result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import TASK_ROWS, Words, arrow_map, compact, cut, mix64, packed, row_count, shingles, small_batches, texts_of

SHINGLE, SIMILARITY = 5, 0.8
BANDS, ROWS = 24, 5
#: Members beyond which a band is dealt anew by rare elements.
CROWDED = 24
#: Ids (8 bytes each) that are broadcast at most; beyond it tables are joined by shuffle.
BROADCAST_IDS = 500_000
#: Links that one task takes at most; beyond it labels travel by joins. Each join is a plan in the driver's memory.
TASK_LINKS = 500_000
#: Types of ids that are broadcast as an array.
INTEGERS = ("tinyint", "smallint", "int", "bigint")

_ODD = np.uint64(0x9E3779B97F4A7C15)
_RANGE = np.uint64(0xA0761D6478BD642F)
_MASK = (1 << 64) - 1


def bags(words: Words, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, shingle and count of every distinct shingle, rows in order, shingles of a row in order."""
    h, row, _ = shingles(words, k)
    h = h.copy()
    at = np.searchsorted(row, np.arange(len(words.count) + 1)).tolist()
    for a, b in zip(at, at[1:], strict=False):
        if b - a > 1:
            h[a:b].sort()
    if not len(h):
        return row, h, row
    first = np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (row[1:] != row[:-1]))))
    return row[first], h[first], np.diff(np.concatenate((first, [len(h)])))


def elements(h: np.ndarray, count: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every occurrence of a shingle as an element of its own, so that multisets become sets; and its row."""
    again = np.repeat(np.arange(len(h)), count)
    nth = np.arange(len(again)) - np.repeat(np.cumsum(count) - count, count)
    return mix64(h[again] + nth.astype(np.uint64) * _ODD), row[again]


def signatures(row: np.ndarray, h: np.ndarray, weight: np.ndarray, rows: int, slots: int = BANDS * ROWS) -> np.ndarray:
    """rows x slots lowest points; infinite for rows without shingles."""
    low = np.full(rows * slots, np.inf)
    if not len(h):
        return low.reshape(rows, slots)
    seed, own, rate, start, top = [mix64(h)], [row], [np.ones(len(h))], [np.zeros(len(h))], [weight.astype(np.float64)]
    j = 1
    heavy = np.flatnonzero(weight > 1)
    while len(heavy):
        begin = float(2 ** (j - 1))
        seed.append(mix64(h[heavy] ^ np.uint64(int(_RANGE) * j & _MASK)))
        own.append(row[heavy])
        rate.append(np.full(len(heavy), begin))
        start.append(np.full(len(heavy), begin))
        top.append(weight[heavy].astype(np.float64))
        j += 1
        heavy = heavy[weight[heavy] > 2 ** (j - 1)]
    seed, own, rate, start, top = (np.concatenate(x) for x in (seed, own, rate, start, top))
    x = np.zeros(len(seed))
    whole = start + rate <= top  # the range lies below the weight altogether
    step = 0
    while len(seed):
        step += 1
        draw = mix64(seed + np.uint64(int(_ODD) * step & _MASK))
        x = x - np.log(((draw >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / rate
        pick = mix64(draw ^ _RANGE)
        slot = ((pick >> np.uint64(32)) * np.uint64(slots) >> np.uint64(32)).astype(np.int64)
        at = own * slots + slot
        if whole.all():
            np.minimum.at(low, at, x)
        else:
            inside = whole | (start + rate * ((pick & np.uint64(0xFFFFFFFF)).astype(np.float64) * 2.0**-32) < top)
            np.minimum.at(low, at[inside], x[inside])
        worst = low.reshape(rows, slots).max(axis=1)
        go = x < worst[own]
        seed, own, rate, start, top, x, whole = (v[go] for v in (seed, own, rate, start, top, x, whole))
    return low.reshape(rows, slots)


def band_keys(low: np.ndarray, bands: int = BANDS, per: int = ROWS) -> np.ndarray:
    """rows x bands hashes of a band's slots and its number."""
    bits = low.view(np.uint64).reshape(len(low), bands, per)
    acc = np.tile(np.arange(bands, dtype=np.uint64), (len(low), 1))
    for i in range(per):
        acc = mix64(acc * _ODD + bits[:, :, i])
    return acc


def sign(docs: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, w1, w2, bands): a 128-bit hash of the words in order (null without words) and the band keys."""
    kind = dict(docs.dtypes)[id_column]

    def make():
        def run(batch):
            words = Words(texts_of(batch.column(1)))
            n = len(words.count)
            keys = band_keys(signatures(*bags(words), n))
            at = np.arange(len(words.hash)) - words.first[words.row]
            both = []
            for salt in (1, 2):
                z = mix64(words.hash + mix64(at.astype(np.uint64) * _ODD + np.uint64(salt)))
                sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(z)))
                both.append(mix64(sums[words.first[1:]] - sums[words.first[:-1]]).view(np.int64))
            none = words.count == 0
            lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * BANDS, pa.int32()), pa.array(keys.view(np.int64).ravel()))
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(both[0], mask=none), pa.array(both[1], mask=none), lists], [id_column, "w1", "w2", "bands"])

        return run

    return arrow_map(docs.select(id_column, text), f"{id_column} {kind}, w1 long, w2 long, bands array<long>", make)


def element_lists(docs: DataFrame, id_column: str, text: str, ids: DataFrame) -> DataFrame:
    """(rep, elements): the element set of the text of every row whose id is one of the ids."""
    kind, few = dict(docs.dtypes)[id_column], broadcast_ids(ids, id_column)
    if few is None:
        docs = joined(docs, ids, id_column, "left_semi")

    def make():
        def run(batch):
            if few is not None:
                batch = batch.filter(pa.array(held(batch.column(0), few.value)))
            words = Words(texts_of(batch.column(1)))
            row, h, count = bags(words)
            e, own = elements(h, count, row)
            offsets = np.searchsorted(own, np.arange(len(words.count) + 1))
            lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(e.view(np.int64)))
            return pa.RecordBatch.from_arrays([batch.column(0), lists], ["rep", "elements"])

        return run

    return arrow_map(docs.select(id_column, text), f"rep {kind}, elements array<long>", make)


def broadcast_ids(ids: DataFrame, column: str):
    """The ids as a sorted array that every worker gets; None if they are many or no integers. The driver holds 8 bytes an id, where
    the hash table of a join takes several times that of its heap."""
    if dict(ids.dtypes)[column] not in INTEGERS or row_count(ids) > BROADCAST_IDS:
        return None
    found = ids.select(F.col(column).cast("long").alias("id")).where("id is not null").toArrow().column(0).to_numpy()
    return ids.sparkSession.sparkContext.broadcast(np.unique(found.astype(np.int64)))


def held(ids: pa.Array, known: np.ndarray) -> np.ndarray:
    """Which of the ids are among the known ones, which are sorted; a null never is."""
    if not len(known):
        return np.zeros(len(ids), dtype=bool)
    there = ids.is_valid().to_numpy(zero_copy_only=False)
    own = pc.fill_null(ids, 0).to_numpy(zero_copy_only=False).astype(np.int64)
    return there & (known[np.minimum(np.searchsorted(known, own), len(known) - 1)] == own)


def joined(df: DataFrame, ids: DataFrame, column: str, how: str) -> DataFrame:
    return df.join(F.broadcast(ids) if row_count(ids) <= BROADCAST_IDS else ids, column, how)


def keep_ids(df: DataFrame, ids: DataFrame, column: str, how: str = "left_semi") -> DataFrame:
    """Semi or anti join on an id; the ids are broadcast only if a count shows that they are few."""
    few = broadcast_ids(ids, column) if dict(df.dtypes)[column] in INTEGERS else None
    if few is None:
        return joined(df, ids, column, how)
    small_batches(df.sparkSession)

    @F.arrow_udf("boolean")
    def known(x: pa.Array) -> pa.Array:
        return pa.array(held(x, few.value))

    return df.where(known(F.col(column)) if how == "left_semi" else ~known(F.col(column)))


def smallest(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Of each of n vertices the smallest one it is connected to by links (a, b). In a turn every component with a smaller neighbour joins it, so at
    most half of those that have any neighbour are left."""
    label = np.arange(n)
    while True:
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            return label
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while (label != (far := label[label])).any():
            label = far


def components_at_once(links: DataFrame) -> DataFrame:
    """components() in one task."""
    kind = dict(links.dtypes)["a"]

    def run(batches):
        parts = [(batch.column(0), batch.column(1)) for batch in batches if batch.num_rows]
        if not parts:
            return
        a, b = (pa.chunked_array(x) for x in zip(*parts, strict=True))
        ids = pc.unique(pa.chunked_array([*a.chunks, *b.chunks]))
        ids = ids.take(pc.sort_indices(ids))
        label = smallest(*(pc.index_in(x, value_set=ids).to_numpy().astype(np.int64) for x in (a, b)), len(ids))
        yield pa.RecordBatch.from_arrays([ids, ids.take(pa.array(label))], ["rep", "label"])

    return cut(links.select("a", "b").coalesce(1).mapInArrow(run, f"rep {kind}, label {kind}"))


def components(links: DataFrame, most: int, count: int | None = None) -> DataFrame:
    """(rep, label) of every end of a link (a, b): the smallest id it is connected to. Labels travel along links and then jump to
    their label's label, so a chain of length n takes about log2(n) rounds; a few links are one task. most: a bound on the ids that are
    linked; count: how many links there are, counted if it isn't given."""
    if dict(links.dtypes)["a"] in (*INTEGERS, "string") and (row_count(links) if count is None else count) <= TASK_LINKS:
        return components_at_once(links)
    both = compact(cut(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), 2 * most))
    labels = compact(cut(both.groupBy(F.col("a").alias("rep")).agg(F.least(F.col("a"), F.min("b")).alias("label")), most))
    while True:
        near = both.join(labels, both.b == labels.rep).groupBy(F.col("a").alias("rep")).agg(F.min("label").alias("near"))
        step = labels.join(near, "rep").select("rep", "label", F.least("label", "near").alias("low"))
        far = labels.select(F.col("rep").alias("low"), F.col("label").alias("far"))
        step = compact(cut(step.join(far, "low", "left").select("rep", F.col("label").alias("old"), F.least("low", F.coalesce("far", "low")).alias("label")), most))
        if step.where("old != label").isEmpty():
            return step.select("rep", "label")
        labels = step.select("rep", "label")


def _overlap(size_a, size_b):
    """Elements that two sets of these sizes must share."""
    return F.lit(SIMILARITY / (1 + SIMILARITY)) * (size_a + size_b) - F.lit(1e-9)


def _buckets(entries: DataFrame, docs: DataFrame, id_column: str, text: str, most: int) -> tuple[DataFrame | None, DataFrame | None, int]:
    """(bucket, rep, rank, size, shared, nth) of every bucket with two members or more, and (rep, elements) of all these members.
    Rank 1 is the most central member, shared counts the elements that others hold too, and nth is the place of the bucket's element
    among the member's by rarity (1 in buckets that are bands)."""
    sizes = entries.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    entries = cut(entries.join(sizes, "bucket"), most * BANDS, 20 * TASK_ROWS)
    members = cut(entries.groupBy("rep").agg(F.max("n").alias("n")), most)
    most = row_count(members)
    if not most:
        return None, None, 0
    texts = cut(element_lists(docs, id_column, text, members.select(F.col("rep").alias(id_column))).dropDuplicates(["rep"]), most, 2_000)
    crowd = members.where(F.col("n") > CROWDED).select("rep")
    # each of these texts becomes hundreds of rows, so they are dealt out evenly, a hundred or so to a task
    deal = max(1, min(-(-row_count(crowd) // 100), 8 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))))
    held = texts.join(crowd, "rep", "left_semi").repartition(deal).select("rep", F.explode("elements").alias("element"))
    held = held.withColumn("holders", F.count("*").over(Window.partitionBy("element")))
    by = Window.partitionBy("rep")
    held = held.select("rep", "element", "holders", F.row_number().over(by.orderBy("holders", "element")).alias("nth"), F.count("*").over(by).alias("size"), F.sum((F.col("holders") > 1).cast("long")).over(by).alias("shared"))
    first = F.col("nth") <= F.col("size") - F.ceil(F.col("size") * F.lit(SIMILARITY) - F.lit(1e-9)) + 1
    rare = held.where((F.col("holders") > 1) & first).select(F.col("element").alias("bucket"), "rep", "size", "shared", "nth")
    size = texts.select("rep", F.size("elements").cast("long").alias("size"))
    few = entries.where(F.col("n") <= CROWDED).select("bucket", "rep").join(size, "rep").select("bucket", "rep", "size", F.col("size").alias("shared"), F.lit(1).alias("nth"))
    together = Window.partitionBy("bucket")
    ranked = few.unionByName(rare).withColumns({"rank": F.row_number().over(together.orderBy(F.desc(F.col("shared") / F.col("size")), "rep")), "most": F.count("*").over(together)})
    return compact(cut(ranked.where("most > 1").drop("most"), most, 1_000)), texts, most


def _compare(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) whose similarity reaches the threshold."""
    left = texts.select(F.col("rep").alias("a"), F.col("elements").alias("x"))
    right = texts.select(F.col("rep").alias("b"), F.col("elements").alias("y"))
    joined = pairs.join(right, "b").join(left, "a")
    return joined.where(F.size(F.array_intersect("x", "y")) >= _overlap(F.size("x"), F.size("y"))).select("a", "b")


def link_classes(entries: DataFrame, docs: DataFrame, id_column: str, text: str, most: int) -> DataFrame | None:
    """(rep, label) of every text that is linked to another; None if there are no links."""
    buckets, texts, most = _buckets(entries, docs, id_column, text, most)
    if buckets is None:
        return None
    labels = None
    done, take = 0, 1
    while True:
        own = buckets if labels is None else buckets.join(labels, "rep", "left")
        own = own.withColumn("label", F.col("rep") if labels is None else F.coalesce("label", "rep"))
        # buckets whose members are of one class are finished, and so are those whose members have all been compared
        mixed = own.groupBy("bucket").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.max("rank").alias("most")).where((F.col("lo") < F.col("hi")) & (F.col("most") > done + 1)).select("bucket")
        own, left = packed(cut(own.join(mixed, "bucket", "left_semi"), most, 1_000))
        if not left:
            return labels
        pivots = own.where((F.col("rank") > done) & (F.col("rank") <= done + take)).select("bucket", *[F.col(c).alias(f"{c}_a") for c in ("rep", "rank", "size", "shared", "nth", "label")])
        # what two sets must share bounds the elements they share with anybody; and where they first meet in order of rarity, enough
        # must be left in both, so a pair that is linked passes in the bucket of its first common element
        enough = _overlap(F.col("size"), F.col("size_a"))
        fit = (
            (F.col("rank") > F.col("rank_a"))
            & (F.col("label") != F.col("label_a"))
            & (F.least("shared", "shared_a") >= enough)
            & (F.col("size") - F.col("nth") + 1 >= enough)
            & (F.col("size_a") - F.col("nth_a") + 1 >= enough)
        )
        pairs = own.join(pivots, "bucket").where(fit).select(F.least("rep_a", "rep").alias("a"), F.greatest("rep_a", "rep").alias("b")).distinct()
        new, found = packed(cut(_compare(pairs, texts), most, 2_000))
        if found:
            # what was linked before is known by its labels
            links = new if labels is None else new.unionByName(labels.select(F.col("rep").alias("a"), F.col("label").alias("b")))
            labels = components(links, most, found if labels is None else found + row_count(labels))
        done, take = done + take, take * 16


def classes(docs: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, class_id, n_copies, kept) of every row: its class, how many rows have the same words, and whether it stands for its class."""
    docs = docs.select(id_column, text)
    signed = cut(sign(docs, id_column, text))
    rows = row_count(signed)
    texts = signed.where("w1 is not null").groupBy("w1", "w2").agg(F.min(id_column).alias("rep"), F.count("*").alias("n_copies"), F.first("bands").alias("bands"))
    texts = cut(texts, rows)
    entries = texts.select("rep", F.explode("bands").alias("bucket"))
    labels = link_classes(entries, docs, id_column, text, rows)
    named = texts.select("w1", "w2", "rep", "n_copies")
    if labels is not None:
        named = named.join(labels, "rep", "left").withColumn("rep", F.coalesce("label", "rep"))
    out = signed.select(id_column, "w1", "w2").join(named.select("w1", "w2", "rep", "n_copies"), ["w1", "w2"], "left")
    class_id = F.coalesce("rep", id_column)
    out = out.select(id_column, class_id.alias("class_id"), F.coalesce("n_copies", F.lit(1)).cast("long").alias("n_copies"), (class_id == F.col(id_column)).alias("kept"))
    return out.coalesce(max(1, -(-rows // TASK_ROWS)))


def deduplicate(docs: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """One row of each class, with all its columns. Rows that repeat an id with the same words are one row."""
    found = cut(classes(docs, id_column, text))
    gone = found.where("not kept").select(id_column)
    twice = cut(found.where("kept").groupBy(id_column).count().where("count > 1").select(id_column), 1)
    rest = keep_ids(docs, gone, id_column, "left_anti")
    if twice.isEmpty():
        return rest
    return keep_ids(rest, twice, id_column, "left_anti").unionByName(keep_ids(rest, twice, id_column).dropDuplicates([id_column]))
