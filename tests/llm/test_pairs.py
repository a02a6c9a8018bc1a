"""Near duplicates and benchmark passages against brute force, and the pipeline as a whole."""

import random
import re
from collections import Counter, defaultdict

import pytest

pytest.importorskip("public_tokenizers")
np = pytest.importorskip("numpy")

from pyspark.sql import functions as F  # noqa: E402

from graphwave.llm import decontaminate, near_dedup  # noqa: E402
from graphwave.llm.common import Words  # noqa: E402


def bag(text):
    w = text.lower().split()
    return Counter(zip(*[w[j:] for j in range(5)], strict=False)) if len(w) >= 5 else Counter([tuple(w)] if w else [])


def weighted(a, b):
    both = sum((a & b).values())
    return both / (sum(a.values()) + sum(b.values()) - both) if both else 0.0


def brute_classes(texts):
    """{id: smallest id of its component} over all pairs."""
    up = {i: i for i in texts}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    bags, holders = {i: bag(t or "") for i, t in texts.items()}, defaultdict(list)
    for i, b in bags.items():
        for s in b:
            holders[s].append(i)
    pairs = {(a, b) for who in holders.values() for k, a in enumerate(sorted(who)) for b in sorted(who)[k + 1 :]}
    for a, b in pairs:
        if weighted(bags[a], bags[b]) >= 0.8:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    return {i: root(i) for i in texts}


def varied(rng, base, edits):
    w = list(base)
    for _ in range(edits):
        w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
    return " ".join(w)


def corpus():
    """Copies, near copies at every distance, groups in which only the original is near all, repeated words, short and empty texts."""
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(3_000)]
    texts, at = {}, 0

    def put(t):
        nonlocal at
        texts[at] = t
        at += 1

    for _ in range(150):
        put(" ".join(rng.choices(vocabulary, k=rng.randrange(6, 200))))
    hub = rng.choices(vocabulary, k=150)
    for k in range(90):
        put(varied(rng, hub, 1 + k % 7))
    put(" ".join(hub))
    other = rng.choices(vocabulary, k=80)
    for _ in range(30):
        put(varied(rng, other, 1))
    for t in ("", None, "one two", "one two", "One TWO", "a b c d e", "a b c d e", "spam " * 500, "spam " * 520, "spam " * 300, "\n \t"):
        put(t)
    put(" ".join(vocabulary[:2_000]))
    put(" ".join(vocabulary[:2_000]) + " end")
    return texts


def test_near_duplicates_equal_brute_force(spark):
    texts = corpus()
    df = spark.createDataFrame([(i, t, "s", i) for i, t in texts.items()], "doc_id long, text string, bands string, rep long")
    got = {r["doc_id"]: r for r in near_dedup.classes(df).collect()}
    want = brute_classes(texts)
    assert {i: r["class_id"] for i, r in got.items()} == want
    assert all(r["kept"] == (r["class_id"] == i) for i, r in got.items())
    kept = near_dedup.deduplicate(df)
    assert kept.columns == df.columns and sorted(r["doc_id"] for r in kept.collect()) == sorted(set(want.values()))


def test_crowded_buckets_equal_brute_force(spark, monkeypatch):
    """The same with every bucket dealt anew by rare elements."""
    monkeypatch.setattr(near_dedup, "CROWDED", 2)
    texts = corpus()
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {r["doc_id"]: r["class_id"] for r in near_dedup.classes(df).collect()} == brute_classes(texts)


def test_near_duplicates_of_nothing(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert near_dedup.classes(df).count() == 0 and near_dedup.deduplicate(df).count() == 0
    twice = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (2, None), (3, None)], "doc_id long, text string")
    assert sorted((r["doc_id"], r["class_id"]) for r in near_dedup.classes(twice).collect()) == [(1, 1), (1, 1), (2, 2), (3, 3)]
    assert sorted(r["doc_id"] for r in near_dedup.deduplicate(twice).collect()) == [1, 2, 3]


def test_signatures_are_unbiased():
    rng = random.Random(1)
    base = [f"w{rng.randrange(400)}" for _ in range(150)]
    texts = [varied(rng, base, k) for k in (0, 1, 2, 4, 7)] + ["x y z q r s " * 40, "x y z q r s " * 30, "x y z q r s " * 3]
    words = Words(texts)
    low = near_dedup.signatures(*near_dedup.bags(words), len(texts), 4_000)
    bags = [bag(t) for t in texts]
    for i in range(len(texts)):
        for j in range(i):
            assert abs((low[i] == low[j]).mean() - weighted(bags[i], bags[j])) < 0.035


def test_a_long_chain_is_one_class(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(99)], "a long, b long")
    assert {r["label"] for r in near_dedup.components(links, 100).collect()} == {0}


def test_components_in_one_task_and_by_joins(spark, monkeypatch):
    """Both ways name every end of a link by the smallest id it is connected to, whatever the type of the ids."""
    rng = random.Random(4)
    pairs = [(rng.randrange(30), rng.randrange(30)) for _ in range(14)] + [(7, 7)]
    label = {i: i for p in pairs for i in p}
    while any(label[a] != label[b] for a, b in pairs):
        for a, b in pairs:
            label[a] = label[b] = min(label[a], label[b])
    links = spark.createDataFrame(pairs, "a long, b long")
    named = links.select(*[F.format_string("n%03d", F.col(c)).alias(c) for c in "ab"])
    assert sorted((r["rep"], r["label"]) for r in near_dedup.components(named, 30).collect()) == sorted((f"n{a:03d}", f"n{b:03d}") for a, b in label.items())
    for most in (near_dedup.TASK_LINKS, 0):
        monkeypatch.setattr(near_dedup, "TASK_LINKS", most)
        assert sorted((r["rep"], r["label"]) for r in near_dedup.components(links, 30).collect()) == sorted(label.items())


def test_smallest_connected_vertex():
    rng = np.random.default_rng(4)
    a, b = rng.integers(0, 3_000, (2, 2_000))
    want = np.arange(3_000)
    while (want[a] != want[b]).any():
        low = np.minimum(want[a], want[b])
        np.minimum.at(want, a, low)
        np.minimum.at(want, b, low)
    assert (near_dedup.smallest(a, b, 3_000) == want).all()
    assert len(near_dedup.smallest(a[:0], b[:0], 0)) == 0


def test_ids_kept_by_array_and_by_join(spark, monkeypatch):
    """Both ways keep the same rows with their types; a null id is never among the ids."""
    rows = [(None, "null"), (-5, "a"), (0, "b"), (0, "b"), (3, "c"), (1 << 40, "d")]
    df = spark.createDataFrame(rows, "id long, text string")
    for most in (near_dedup.BROADCAST_IDS, 0):
        monkeypatch.setattr(near_dedup, "BROADCAST_IDS", most)
        for ids in ([0, 0, 1 << 40, 9], [None, -5], []):
            listed = spark.createDataFrame([(i,) for i in ids], "id long")
            inside = [r for r in rows if r[0] is not None and r[0] in ids]
            assert sorted(map(tuple, near_dedup.keep_ids(df, listed, "id").collect())) == sorted(inside)
            assert sorted(map(str, map(tuple, near_dedup.keep_ids(df, listed, "id", "left_anti").collect()))) == sorted(str(r) for r in rows if r not in inside)


def test_near_duplicates_leave_few_plans_to_the_driver(spark):
    """Every job costs the driver a plan. These texts took 188 jobs when labels travelled by joins and rows were counted by SQL."""
    texts = corpus()
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    spark.sparkContext.setJobGroup("plans", "plans")
    try:
        near_dedup.classes(df).collect()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert 0 < len(spark.sparkContext.statusTracker().getJobIdsForGroup("plans")) < 130


# ---------------------------------------------------------------------------------------------------------------------


def plain(text):
    return re.findall(r"[a-z0-9\x80-\U0010ffff]+", (text or "").lower())


def brute_leaks(items, texts):
    """(doc, item) by trying every window of the item's length."""
    out = set()
    for i, item in items.items():
        w = plain(item)
        k = min(5, len(w))
        if not w:
            continue
        want = Counter(tuple(w[j : j + k]) for j in range(len(w) - k + 1))
        for d, text in texts.items():
            v = plain(text)
            if len(v) < k:
                continue
            for start in range(max(1, len(v) - len(w) + 1)):
                part = v[start : start + len(w)]
                if weighted(Counter(tuple(part[j : j + k]) for j in range(len(part) - k + 1)), want) >= 0.8:
                    out.add((d, i))
                    break
    return out


def leak_case():
    rng = random.Random(5)
    v = [f"v{i}" for i in range(500)]
    items = {i: " ".join(rng.choices(v, k=rng.randrange(12, 50))) for i in range(25)} | {90: "", 91: None, 92: "two words", 93: "a b c d e f g"}
    texts = {}
    for d in range(120):
        body = rng.choices(v, k=rng.randrange(0, 150))
        kind = d % 6
        if kind < 4:
            item = items[d % 25].split()
            if kind == 1:
                item[rng.randrange(len(item))] = "changed"
            elif kind == 2:
                item = item[: max(1, int(len(item) * rng.uniform(0.6, 1)))]
            elif kind == 3:
                item = [w.upper() + "!!" for w in item]
            at = rng.randrange(len(body) + 1)
            body[at:at] = item
        texts[d] = " ".join(body)
    texts |= {200: None, 201: "", 202: "here are Two, words", 203: "a b c d e f g", 204: "A-B-C D E F G h", 205: "two"}
    return items, texts


def test_leaks_equal_brute_force(spark):
    items, texts = leak_case()
    docs = spark.createDataFrame([(d, t, 0.5) for d, t in texts.items()], "doc_id long, text string, similarity double")
    bench = spark.createDataFrame(list(items.items()), "item_id long, text string")
    got = decontaminate.find_leaks(docs, bench).collect()
    want = brute_leaks(items, texts)
    assert {(r["doc_id"], r["item_id"]) for r in got} == want and len(got) == len(want)
    assert all(r["similarity"] >= 0.8 and r["hamming"] <= decontaminate.RADIUS for r in got)
    kept = decontaminate.clean(docs, bench)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == set(texts) - {d for d, _ in want}


def test_long_texts_and_long_items(monkeypatch):
    """Windows over several pieces, many items of one length, an item longer than a piece, and repeated words."""
    rng = random.Random(8)
    v = [f"u{i}" for i in range(3_000)]
    items = {i: " ".join(rng.choices(v, k=30)) for i in range(150)} | {500: " ".join(rng.choices(v, k=700)), 501: "na " * 40, 502: "one two"}
    body = rng.choices(v, k=9_000)
    for at, i in ((0, 3), (252, 77), (4_000, 149), (8_960, 8)):
        body[at : at + 30] = items[i].split()
    body[5_000:5_700] = items[500].split()
    body[5_300] = "changed"
    texts = [" ".join(body), "na " * 300, items[500], " ".join(items[500].split()[:600]), "x one Two y"]
    got = decontaminate.Items(list(items), list(items.values())).search(texts)
    monkeypatch.setattr(decontaminate, "PIECE", 256)
    assert sorted(decontaminate.Items(list(items), list(items.values())).search(texts)) == sorted(got)
    assert {(r, i) for r, i, *_ in got} == {(0, 3), (0, 77), (0, 149), (0, 8), (0, 500), (1, 501), (2, 500), (3, 500), (4, 502)}
    assert {(r, i): at for r, i, at, *_ in got if r == 0} == {(0, 3): 0, (0, 77): 252, (0, 149): 4_000, (0, 8): 8_960, (0, 500): 5_000}


def test_items_in_blocks(spark, monkeypatch):
    items, texts = leak_case()
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    bench = spark.createDataFrame(list(items.items()), "item_id long, text string")
    blocks = list(decontaminate.item_blocks(bench, most=1_000))
    assert len(blocks) > 2 and sum(map(len, blocks)) == 27
    one = {tuple(r) for r in decontaminate.find_leaks(docs, bench).collect()}
    assert {tuple(r) for r in decontaminate.find_leaks(docs, bench, most=1_000).collect()} == one
    assert {r[0] for r in decontaminate.clean(docs, bench, most=1_000).select("doc_id").collect()} == set(texts) - {r[0] for r in one}
    assert decontaminate.find_leaks(docs.limit(0), bench).count() == 0 and decontaminate.find_leaks(docs, bench.limit(0)).count() == 0


def test_block_index_misses_nothing():
    rng = np.random.default_rng(2)
    items = rng.integers(0, 2**63, 50).astype(np.uint64)
    windows = np.concatenate([items ^ (np.uint64(1) << rng.integers(0, 64, 50).astype(np.uint64)) for _ in range(4)])
    for _ in range(14):
        windows = windows ^ (np.uint64(1) << rng.integers(0, 64, len(windows)).astype(np.uint64))
    for radius in (3, 7, 15, 23):
        w, i, apart = decontaminate.Index(items, radius).within(windows)
        got = set(zip(w.tolist(), i.tolist(), strict=True))
        assert got == {(a, b) for a in range(len(windows)) for b in range(50) if int(windows[a] ^ items[b]).bit_count() <= radius}


# ---------------------------------------------------------------------------------------------------------------------


def test_pipeline_equals_brute_force(spark, tiny, tmp_path):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    tiktoken = pytest.importorskip("tiktoken")
    import hashlib

    import public_tokenizers

    from graphwave.llm import bpe, language_id, pii

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    rows = {r["doc_id"]: r["text"] for r in docs.collect()}
    refused = {r["doc_id"] for r in language_id.identify(docs, language_id.train(docs)).where("rejected").collect()}
    texts = {i: t for i, t in rows.items() if i not in refused}
    want = brute_classes(texts)
    texts = {i: t for i, t in texts.items() if want[i] == i}
    items = {r["item_id"]: r["text"] for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()}
    leaked = {d for d, _ in brute_leaks(items, texts)}
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.parse_ranks(bpe.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))), special_tokens={})
    from tests.llm.test_texts import all_parts, brute_assign

    key, found = pii.session_key(spark), all_parts([t for i, t in texts.items() if i not in leaked])
    drawn = {x: (n, found[x]) for x, (n, _) in brute_assign(found, key).items()}
    expected = {}
    for i, t in texts.items():
        if i not in leaked:
            new, _ = pii.replace_text(t, drawn, key)
            expected[i] = (hashlib.sha256(",".join(map(str, library.encode_ordinary(new))).encode()).hexdigest(), hashlib.sha256(new.encode()).hexdigest())
    got = {r["doc_id"]: (r["ids_sha256"], r["decoded_sha256"]) for r in corpus_pipeline.run(spark, tiny).collect()}
    assert got == expected
    before = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        before = stage(spark, before, tiny)
        assert before.columns == docs.columns


def test_pipeline_edges(spark, tiny, tmp_path):
    """Null ids, texts and languages, empty and repeated rows, a very long text, columns with the stages' own names; no items; no rows."""
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    good = [r["text"] for r in spark.read.parquet(f"{tiny}/documents.parquet").where("length(text) > 300").limit(12).collect()]
    rows = [(i, t, "en", "s", 1, 7, "x") for i, t in enumerate(good)] + [(0, good[0], "en", "s", 1, 7, "x"), (None, good[1], None, None, None, None, None), (50, None, "en", "s", 0, 7, "x"), (51, "", "en", "s", 0, 7, "x")]
    rows += [(60, " ".join(good) * 40, "en", "s", 1, 7, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, rep int, entities string")
    items = spark.read.parquet(f"{tiny}/benchmark.parquet")
    for name, docs, bench in (("a", df, items.limit(0)), ("b", df.limit(0), items)):
        folder = f"{tmp_path}/{name}"
        docs.write.parquet(f"file://{folder}/documents.parquet")
        bench.write.parquet(f"file://{folder}/benchmark.parquet")
        before = spark.read.parquet(f"file://{folder}/documents.parquet")
        for _, stage in corpus_pipeline.STAGES[:-1]:
            before = stage(spark, before, f"file://{folder}")
            assert before.columns == docs.columns
        got = corpus_pipeline.run(spark, f"file://{folder}")
        ids = [r["doc_id"] for r in got.collect()]
        assert len(ids) == before.count() and set(ids) <= {r[0] for r in rows}
        assert (len(ids) > 0) == (name == "a") and ids.count(0) <= 1
