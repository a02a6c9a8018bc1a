import re
from collections import Counter

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

pytest.importorskip("ahocorasick")

from pyspark.sql import functions as F  # noqa: E402

from graphwave.llm import license_scan, quality_rules  # noqa: E402

WORDS = st.lists(st.sampled_from(["CC", " by", "-", "BY ", "general ", "public ", "License", "all", " rights", " Reserved", "é", "\n", "7", "_", "K", "İ", "\x85"]), max_size=40).map("".join)


@settings(max_examples=300, deadline=None)
@given(text=WORDS)
def test_base_places(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    places, labels = [], set()
    for phrase, label in license_scan.BASE.items():
        p = phrase.split()
        for i in range(len(words) - len(p) + 1):
            if words[i : i + len(p)] == p:
                places.append(i)
                labels.add(label)
    n, base, first, last, own, every, score, allows, expressions, _ = license_scan.Scanner().scan(text)
    line = f" {' '.join(words)} "
    notices = [(p, label) for p, label in [*license_scan.NOTICES.items(), *license_scan.BASE.items()] for _ in range(len(re.findall(f"(?= {p} )", line)))]
    assert every == sorted({label for _, label in notices}) and expressions == []
    known = [v for v in (license_scan.terms(x) for x in every) if v is not None]
    assert allows == min(known, default=None) and score == ((1 - 0.5 ** len(notices)) * license_scan.OPEN[allows] if notices else 0)
    assert (n, base, first, last, own) == (len(words), len(places), min(places, default=None), max(places, default=None), sorted(labels))
    assert set(own) <= set(every) and 0 <= score <= 1


@pytest.mark.parametrize(
    "written, postfix, allows",
    [
        ("MIT OR Apache-2.0", ["mit", "apache-2.0", "or"], 2),
        ("MIT AND (GPL-2.0-only WITH Classpath-exception-2.0)", ["mit", "gpl-2.0-only", "classpath-exception-2.0", "with", "and"], 1),
        ("MIT OR GPL-3.0 AND CC-BY-NC-4.0", ["mit", "gpl-3.0", "cc-by-nc-4.0", "and", "or"], 2),
        ("GPL-3.0 AND CC-BY-NC-4.0", ["gpl-3.0", "cc-by-nc-4.0", "and"], 0),
        ("MIT AND", None, None),
        ("(MIT", None, None),
        ("Unheard-Of", ["unheard-of"], None),
        ("", None, None),
    ],
)
def test_expressions(written, postfix, allows):
    found = license_scan.parse_expression(written)
    assert (found.postfix, found.allows) == (postfix, allows)


@pytest.mark.parametrize("written, allows, score", [("MIT OR GPL-3.0", 2, 1.0), ("MIT AND GPL-3.0", 1, 0.75), ("GPL-3.0 AND CC-BY-NC-4.0", 0, 0.25), ("LicenseRef-own", None, 0.25), ("(MIT", None, 0.25)])
def test_the_value_of_an_expression_decides(written, allows, score):
    found = license_scan.Scanner().scan(f"# SPDX-License-Identifier: {written}\nx = 1")
    assert (found[7], found[6]) == (allows, score)


def test_licence_frame(spark):
    texts = [None, "", "// SPDX-License-Identifier: MIT OR Apache-2.0\ncode", "All rights reserved. all rights reserved", "word " * 20_000 + "cc by nc"]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, labels string")
    got = {r["doc_id"]: r for r in license_scan.scan(df).collect()}
    assert (got[0]["n_words"], got[0]["first_word"], got[0]["labels"], got[0]["score"]) == (0, None, "", 0.0)
    assert got[1]["n_words"] == 0 and got[2]["labels"] == "apache-2.0,mit" and got[2]["score"] == 1.0
    assert (got[3]["n_base"], got[3]["first_word"], got[3]["last_word"]) == (2, 0, 3)
    assert (got[4]["first_word"], got[4]["base_labels"], got[4]["labels"]) == (20_000, "cc-by", "cc-by,cc-by-nc")
    assert license_scan.scan(df.limit(0)).count() == 0


@settings(max_examples=300, deadline=None)
@given(text=st.lists(st.sampled_from(["a", "b", " ", "\n", "\t", "\x0b", "é", "日", "\x85", "\xa0", "#", "$ ", "a b a "]), max_size=60).map("".join))
def test_counts(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    windows = list(zip(words, words[1:], words[2:], strict=False))
    often, covered = Counter(windows), set()
    for i, w in enumerate(windows):
        if often[w] > 1:
            covered |= {i, i + 1, i + 2}
    c = quality_rules.counted(text)
    assert (c.n_words, c.word_chars, c.n_symbols, c.n_dup_lines, c.n_repeat_words) == (len(words), sum(map(len, words)), sum(x in "#*$%&|<>" for x in text), dup, len(covered))


def test_distance():
    import numpy as np

    assert quality_rules.distance(np.array([1.0, 0]), np.array([0, 1.0]))[0] == 1
    assert quality_rules.distance(np.array([2.0, 2]), np.array([1.0, 1]))[0] == 0
    assert quality_rules.distance(np.array([0.0, 0]), np.array([1.0, 1]))[0] == 1


def brute_rules(rows):
    """{id: (nearest, char distance, word distance, kept)} in plain Python and NumPy."""
    import numpy as np

    q = quality_rules
    k = len(q.CLASSES)
    words = {i: q.plain_words((t or "").encode().split()) for i, t, _ in rows}
    chars = {i: q.char_histograms([t or ""])[0] for i, t, _ in rows}
    langs = sorted({x for *_, x in rows if x})
    counts = {x: Counter(w for i, _, y in rows if y == x for w in words[i] if 0 < len(w) <= q.LONGEST) for x in langs}
    order = {x: sorted(c, key=lambda w: (-c[w], w)) for x, c in counts.items()}
    common = sorted({w for x in langs for w in order[x][: q.TOP]})
    hist = lambda own: np.array([*(own.count(w) for w in common), sum(w not in common for w in own)], float)
    ref = {}
    for x in langs:
        total = sum(len(words[i]) for i, _, y in rows if y == x)
        known = [counts[x][w] if w in order[x][: q.DEEP] else 0 for w in common]
        ref[x] = (sum(chars[i] for i, _, y in rows if y == x), np.array([*known, total - sum(known)], float))
    found, groups = {}, {}
    for i, t, x in rows:
        c = q.counted(t or "")
        if langs:
            each = [(q.distance(chars[i], ref[y][0])[0], q.distance(hist(words[i]), ref[y][1])[0], y) for y in langs]
            cd, wd, near = min(each, key=lambda e: (e[0] + e[1], e[2]))
        else:
            cd = wd = 0.0
            near = None
        failed = c.n_words < 50 or 2 * c.n_repeat_words > c.n_words
        judged = c.n_words >= q.MIN_WORDS and c.word_chars >= q.MIN_CHARS
        size = sum(c.n_words >= n for n in q.LENGTHS)
        found[i] = (near, cd, wd, failed, judged, size)
        if x and not failed and near and judged:
            for key in ((near, size), (near, None)):
                groups.setdefault(key, []).append((round(cd, 4), round(wd, 4)))

    def limit(near, size, which):
        own = groups.get((near, size), [])
        own = own if len(own) >= q.LEAST else groups.get((near, None), [])
        if not own:
            return np.inf
        mid, high = np.quantile([o[which] for o in own], [0.5, 0.84])
        return mid + q.SPREAD * (high - mid)

    assert k == 9
    return {i: (near, round(cd, 9), round(wd, 9), not failed and not (judged and (cd > limit(near, size, 0) or wd > limit(near, size, 1)))) for i, (near, cd, wd, failed, judged, size) in found.items()}


def test_rules_frame(spark):
    import random

    r = random.Random(1)
    vocabulary = {"en": "the river of stones and a house was near it with many birds that sang".split(), "de": "der fluss und die steine an das haus war mit vielen voegeln in dem".split()}
    rows = []
    for i in range(240):
        lang = ("en", "de")[i % 2]
        n = r.choice([40, 55, 58, 62, 70, 90, 120, 180, 260, 400, 1200])
        own = [r.choice(vocabulary[lang]) + r.choice(["", "", "", ".", ","]) + r.choice(["", "", "x", "yz"]) for _ in range(n)]
        if i % 12 == 0:
            own = [w + r.choice(["###", "$$$", "%%%"]) for w in own]
        if i % 15 == 0:
            own = [x for w in own for x in (f"{w}{r.randrange(10**6)}q", "|")]
        rows.append((i, " ".join(own), None if i % 7 == 0 else lang))
    rows += [(300, None, "en"), (301, "", None), (302, "too short", "en"), (303, "word " * 60_000, "en"), (304, "a" * 300_000, "de"), (305, rows[5][1], "en"), (306, "\U0001d518 " * 80, "en")]
    df = spark.createDataFrame([(*x, True, 1) for x in rows], "doc_id long, text string, lang string, kept boolean, nearest int")
    got = {x["doc_id"]: x for x in quality_rules.judge(df).collect()}
    want = brute_rules(rows)
    assert {i: (x["nearest"], round(x["char_distance"], 9), round(x["word_distance"], 9), x["kept"]) for i, x in got.items()} == want
    junk = {i for i in range(240) if i % 12 == 0 or i % 15 == 0}
    judged = {i for i in range(240) if got[i]["n_words"] >= quality_rules.MIN_WORDS and not got[i]["base_failed"]}
    print(len(judged & junk), sum(got[i]["kept"] for i in judged & junk), len(judged - junk), sum(not got[i]["kept"] for i in judged - junk))
    assert sum(got[i]["kept"] for i in judged & junk) <= len(judged & junk) / 3 and sum(not got[i]["kept"] for i in judged - junk) <= 3
    short = {i for i in range(240) if 50 <= got[i]["n_words"] < quality_rules.MIN_WORDS and not got[i]["base_failed"]}
    assert short and all(got[i]["kept"] for i in short)  # the guard
    assert not got[300]["kept"] and got[301]["base_failed"] and got[302]["base_failed"]
    none = quality_rules.judge(df.withColumn("lang", F.lit(None).cast("string")))
    assert none.where("kept <> (NOT base_failed)").count() == 0
    assert quality_rules.judge(df.limit(0)).count() == 0
