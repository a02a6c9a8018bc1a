"""Language identification, personal data, web pages and the language model."""

import random
import re
import time

import pytest

pytest.importorskip("numpy")

from pyspark.sql import functions as F  # noqa: E402

from graphwave.llm import html_extract, language_id, pii, quality_lm  # noqa: E402


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet")


@pytest.fixture(scope="module")
def model(documents):
    return language_id.train(documents)


def test_held_out_accuracy(documents, model):
    found = language_id.identify(documents, model).join(documents.select("doc_id", "lang"), "doc_id").where(language_id.is_held_out())
    assert found.count() > 100
    assert found.where("lang = lang_pred").count() / found.count() > 0.97


def test_probabilities_sum_to_one(model):
    """Over all letters that a language's model knows, and the share that is left to unknown ones."""
    import numpy as np

    letters = np.unique(model.levels[0][-1].grams * np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64)))
    for history in ("the", "zzz", "qu "):
        base = sum(ord(c) << (16 * (3 - i)) for i, c in enumerate(history))
        p = language_id._resolve(model.levels[0], letters | np.uint64(base), model.letters)
        assert 0.97 < p.sum() <= 1.0 + 1e-9


def test_texts_without_letters(spark, model):
    rows = [(1, None, "a"), (2, "", "a"), (3, "123 ... 456", "a"), (4, "the and of them there", "a"), (4, "the and of them there", "a"), (5, "the and of them there " * 5_000, "a")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang_pred string")
    got = [tuple(r) for r in language_id.identify(df, model).select("doc_id", "lang_pred", "score", "rejected").orderBy("doc_id").collect()]
    assert [r[1:] for r in got[:3]] == [("und", 0.0, True)] * 3
    assert got[3] == got[4] and got[3][1] == "en" and got[5][1] == "en" and all(0 <= r[2] <= 1 for r in got)
    assert language_id.identify(df.limit(0), model).count() == 0
    assert sorted(r["doc_id"] for r in language_id.accepted(df, model).collect()) == [4, 4, 5]


def test_unknown_language_is_rejected(model):
    _, _, _, reject = model.predict(["Жили были старик со старухой у самого синего моря " * 5, "xqzj kvwx zzqk jxvq wkqz " * 20])
    assert reject.all()


@pytest.mark.parametrize("left_out", ["de", "en", "es", "fr"])
def test_a_language_left_out_of_training_is_rejected(spark, left_out):
    """Nearly all texts of a language that wasn't learned go, and nearly all of the learned ones stay."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").where("length(text) >= 200")
    model = language_id.train(docs.where(F.col("lang") != left_out))
    found = language_id.identify(docs, model).join(docs.select("doc_id", "lang"), "doc_id").where(language_id.is_held_out())
    share = dict(found.groupBy((F.col("lang") == left_out).alias("unknown")).agg(F.avg(F.col("rejected").cast("int"))).collect())
    print(left_out, share)
    assert share[True] > 0.97 and share[False] < 0.03


def test_letters_beyond_the_basic_plane_stay_apart():
    found, _ = language_id.normalised(["\U00010400\U00010401\U00012000 a"])
    assert len(set(found.tolist()) - {32}) == 4


def test_training_leaves_no_model_to_the_driver(spark, documents, monkeypatch):
    """What training broadcasts is gone when it ends; only the finished model is left."""
    made, own = [], type(spark.sparkContext).broadcast
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, value: made.append(own(self, value)) or made[-1])
    assert language_id.train(documents).limit
    assert made and not any(x._jbroadcast.isValid() for x in made)


def test_no_training_rows(spark):
    df = spark.createDataFrame([(1, "some text", None)], "doc_id long, text string, lang string")
    empty = language_id.train(df)
    assert [tuple(r)[1:3] for r in language_id.identify(df, empty).collect()] == [("und", 0.0)]


# ---------------------------------------------------------------------------------------------------------------------


KEY = b"a key of the test"


def test_surrogates_keep_the_format():
    text = "Mail anna.m@Foo.org or ANNA.M@foo.org, call +44 (20) 7946-0018 or +44 20 7946 0018, pay 4111 1111 1111 1111 from 10.1.22.133, token = \"0123456789abcdef0123456789abcdef01234567\"."
    new, spans = pii.replace_text(text, {}, KEY)
    assert [k for *_, k in spans] == ["email", "email", "phone", "phone", "card", "ipv4", "secret"]
    parts = [new[a:b] for a, b, _ in spans]
    assert parts[0].lower() == parts[1].lower() and parts[0].endswith(".org") and parts[1] != parts[1].lower()
    assert re.sub(r"\D", "", parts[2]) == re.sub(r"\D", "", parts[3]) and re.fullmatch(r"\+4\d \(\d\d\) \d{4}-\d{4}", parts[2])
    assert re.fullmatch(r"\d{4}( \d{4}){3}", parts[4]) and pii.luhn(parts[4].replace(" ", "")) and re.fullmatch(r"\d\d\.\d\.\d\d\.\d{3}", parts[5])
    assert re.fullmatch("[0-9a-f]{40}", parts[6])
    assert not set(parts) & {text[a:b] for a, b, _ in pii.mentions(text)}
    assert re.sub("x", "", new[: spans[0][0]]) == "Mail "
    assert pii.replace_text(text, {}, b"another key")[0] != new


def test_names_keep_gender_and_script():
    new, spans = pii.replace_text("Mr. John Smith met Mrs. Smith; Иван Петров met Анна Петрова.", {}, KEY)
    names = [new[a:b] for a, b, _ in spans]
    assert len(names) == 4
    assert names[0].split()[0] in pii.GIVEN["latin", "m"] and names[0].split()[1] == names[1]
    assert names[2].split()[0] in pii.GIVEN["cyrillic", "m"] and names[3].split()[0] in pii.GIVEN["cyrillic", "f"]
    assert names[3].split()[1] == names[2].split()[1] + "а"  # one family in both its forms


@pytest.mark.parametrize("text", ["Priya Raman", "Olumide Adeyemi", "Wei Zhang", "Fatima Khan", "Karl Nyström", "my name is Zorb Quell", "Zorb Quell <z.quell@foo.org>", "Best regards,\nZorb Quell"])
def test_names_beyond_titles(text):
    assert "name" in [k for *_, k in pii.mentions(text)]


@pytest.mark.parametrize("text", ["Version 4.0.1 of 2024-01-02 10:20:30 costs 1,234,567.89", "See 1.2.3.4.5 and 999.1.1.1", "GNU General Public License, version 3.", "a @ b", "key: value", "", "password: --------", "pwd=________", "number 9807915762804490 fails its check digit", "The House Of Lords"])
def test_clean_texts_stay(text):
    assert pii.replace_text(text, {}, KEY) == (text, [])


def all_parts(texts):
    """{(kind, canon): gender} of all entities."""
    found = {}
    for t in texts:
        for a, b, kind in pii.mentions(t or ""):
            for k, canon, gender in pii.parts(kind, t[a:b], t[max(0, a - 24) : a]):
                found[k, canon] = max(found.get((k, canon), ""), gender)
    return found


def brute_assign(found, key=KEY):
    """{(kind, canon): (attempt, made)} in plain Python, by rounds."""
    attempt = dict.fromkeys(found, 0)
    while True:
        made = {x: pii.surrogate(x[0], x[1], n, key, found[x]) for x, n in attempt.items()}
        first = {}
        for x, m in made.items():
            first[x[0], m] = min(first.get((x[0], m), (attempt[x], x[1])), (attempt[x], x[1]))
        bad = [x for x, m in made.items() if first[x[0], m] != (attempt[x], x[1]) or (x[0] != "given" and (x[0], m) in found)]
        if not bad:
            return {x: (attempt[x], m) for x, m in made.items()}
        for x in bad:
            attempt[x] += 1


def test_clashing_surrogates_are_drawn_again(spark, monkeypatch):
    """All 81 addresses of a small shape, secrets of one digit, many names: every surrogate differs from all others and from all that occurs,
    and all are as a plain loop finds them. Ids are null or repeat, and columns have the result's names."""
    texts = [f"host {a}.{b}.1.1 up" for a in range(1, 10) for b in range(1, 10)] + [f"pwd: {k}--------" for k in range(10)]
    texts += [f"Mrs. {g} Smith and Mr. Jones{k}, {g} Brown" for k, g in enumerate(["Zora", "Quilla", "Mabel", "Anna", "Laura", *[f"Given{c}" for c in "abcdefghijklmnopqrstuvwxyz"]])]
    texts += ["password: --------", "Anna Smith. " * 20_000, "", None]
    rows = [(None if i % 3 else i % 7, t, "x", 7) for i, t in enumerate(texts * 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, kind string, entities long")
    given = pii.assign(pii.entities(df), KEY).collect()
    found = all_parts(texts)
    want = brute_assign(found)
    assert {(r["kind"], r["canon"]): (r["attempt"], r["made"]) for r in given} == want
    assert len({(k, m) for (k, _), (_, m) in want.items()}) == len(want) and found["given", "zora"] == "f"
    drawn = {x: (n, found[x]) for x, (n, _) in want.items()}
    expected = sorted(repr((i, t and pii.replace_text(t, drawn, KEY)[0], k, e)) for i, t, k, e in rows)
    few = pii.pseudonymise(df, KEY)
    assert few.columns == ["doc_id", "text", "kind", "entities", "n_entities", "entities_"]
    assert sorted(repr(tuple(r)[:4]) for r in few.collect()) == expected
    monkeypatch.setattr(pii, "BROADCAST_ROWS", -1)
    many = pii.pseudonymise(df, KEY)
    assert many.columns == few.columns and sorted(map(repr, many.collect())) == sorted(map(repr, few.collect()))
    assert pii.pseudonymise(df.limit(0), KEY).count() == 0


# ---------------------------------------------------------------------------------------------------------------------

def built_page(r):
    """A page made of parts, and the text of its article by construction."""
    words = lambda n: " ".join(r.choices("stone river house bird &amp; over café &lt;b&gt; under &#233;t&eacute; seven".split(), k=n))
    plain = lambda t: " ".join(t.replace("&amp;", "&").replace("&lt;", "<").replace("&gt;", ">").replace("&#233;", "é").replace("&eacute;", "é").split())
    blocks, html = [], ""
    for _ in range(r.randrange(3, 9)):
        kind, text = r.choice(["p", "p", "p", "h2", "li", "blockquote", "open", "math"]), f"{words(r.randrange(12, 60))}, {words(5)}."
        blocks.append(plain(text))
        if kind == "li":
            html += f"<ul><li>{text}</li></ul>"
        elif kind == "open":  # a paragraph that isn't closed, with inline marks
            html += f"\n<P class='x'>  <b>{text}</b>\n"
        elif kind == "math":
            html += f"<p>{text} <math><mi>a</mi><mo>+</mo><mi>b</mi></math></p>"
            blocks[-1] += " a+b"
        else:
            html += f"<{kind}>{text}</{kind}>"
        if r.random() < 0.3:
            html += r.choice(["<script>var x = '<p>no</p>';</script>", "<!-- <p>no</p> -->", "<div class='ad'>Buy now</div>", "<aside>By the way</aside>", "<form><p>Your name</p><input></form>", "<style>p{}</style>", "<div class=related><a href=1>One more</a> <a href=2>Two more</a></div>"])
    around = lambda: r.choice(["", "<nav><ul><li><a href='/a'>A</a></li></ul></nav>", "<header><p>The site</p></header>", "<div class='sidebar'><p>Some words beside, some more words, and even more of them.</p></div>", "<div id='cookie-notice'>We use cookies.</div>"])
    holder = r.choice(["article", "main", "div class='post-content'"])
    html = f"<html><head><title>T</title></head><body>{around()}{around()}<{holder}>{html}</{holder.split()[0]}>{around()}<div class='comments'><p>First, and a long remark, with commas, of a reader who has much to say about it all.</p></div><footer>End</footer></body></html>"
    return html, "\n\n".join(blocks)


def test_built_pages_equal_their_article():
    r = random.Random(4)
    for _ in range(300):
        html, want = built_page(r)
        assert html_extract.extract_text(html) == want


@pytest.mark.parametrize(
    "page",
    ["<a " * 80_000, '<a href="x ' * 80_000, '<a href="x ' * 80_001 + ">", "<div>" * 20_000 + "</x>" * 20_000, "<span>" * 20_000 + "<hr>" * 20_000, "<div>" + "<span>" * 20_000 + "x<hr>" * 20_000, "<!-- " * 50_000, "<!" * 50_000, "<a b='x> " * 50_000, '<a "<b >" ' * 30_000, "<li>" * 30_000],
    ids=range(11),
)
def test_broken_pages_take_linear_time(page):
    began = time.process_time()
    html_extract.extract_text(page)
    assert time.process_time() - began < 5


def test_soft_words_are_judged_by_content():
    prose = "Mind that this paragraph is part of the article and says something that readers have to know, as its author meant."
    page = f"<article><p>{prose}</p><div class='alert'><p>{prose}</p></div><div class='share'>Share this</div><div class='related'><a href=1>{prose}</a></div><div class='comments'><p>{prose}</p></div></article>"
    assert html_extract.extract_text(page) == f"{prose}\n\n{prose}"


PAGES = [
    (None, ""),
    ("", ""),
    ("just text < 5 &amp; more", "just text < 5 & more"),
    ("<p>a<p>b", "a\n\nb"),
    ("<div>" * 5_000 + "deep" + "</div>" * 5_000, "deep"),
    ("<script>var t='</p>';</script><style>p{}</style><noscript>x</noscript>", ""),
    (
        '<html class="js sidebar"><body class="has-menu"><header><h1>Site</h1></header><div id="cookie-notice">We use cookies, and more cookies, really.</div><div class="wrap content-sidebar">'
        '<div class="sidebar"><p>Side text that is long, with commas, many, many, commas and so on and so forth.</p></div><div class="post"><h2>Title &amp; more</h2>'
        "<p>Hello, this is   the first paragraph &lt;b&gt;, with an<br>entity &eacute; and commas, yes.</p><ul><li>one</li><li>two <a href=x>link</a></li></ul><p>Short.</p></div>"
        '<div id="comments"><p>I disagree with it, he said, she said, at great length, for a while.</p></div></div><footer>foot</footer></body></html>',
        "Title & more\n\nHello, this is the first paragraph <b>, with an entity é and commas, yes.\n\none\n\ntwo link\n\nShort.",
    ),
    (
        "<body><main><article><header><p>By X</p></header><h1>T</h1><section><p>Para one, long enough to count for the score.</p></section><section><p>x</p><table><tr><td>a<td>b<tr><td>c</table></section>"
        '<aside>no</aside><form>f</form></article><section class="comments"><p>c, c, c, c, long enough to be counted here.</p></section></main>',
        "T\n\nPara one, long enough to count for the score.\n\nx\n\na\n\nb\n\nc",
    ),
    ("<nav>Menu</nav><article><p>Short one.</p></article><div class='ad'>Buy this now, it is cheap, good, and long enough to count.</div>", "Short one."),
    ("<!-- <p>no</p> --><!DOCTYPE html><p>one &#233;&#x41;&nbsp; two</p><!-- open", "one éA two"),
]


@pytest.mark.parametrize("source, text", PAGES)
def test_pages(source, text):
    assert html_extract.extract_text(source) == text


def test_pages_frame(spark):
    df = spark.createDataFrame([(i, f"u{i}", s, "t") for i, (s, _) in enumerate(PAGES)], "page_id long, url string, html string, text string")
    got = {r["page_id"]: (r["url"], r["text"], r["n_chars"]) for r in html_extract.extract(df).collect()}
    assert got == {i: (f"u{i}", t, len(t)) for i, (_, t) in enumerate(PAGES)}
    assert html_extract.extract(df.limit(0)).count() == 0


# ---------------------------------------------------------------------------------------------------------------------


def plain_model(texts):
    """Modified Kneser-Ney by dictionaries: share of each gram and weight of each context, by the definition."""
    from collections import Counter, defaultdict

    full = Counter(g for t in texts for g in quality_lm.grams([t])[0].tolist())
    levels = {quality_lm.ORDER: full}
    for k in range(quality_lm.ORDER - 1, 0, -1):
        levels[k] = Counter(g & ((1 << (12 * k)) - 1) for g in levels[k + 1])
    out = {}
    for k, counts in levels.items():
        n = [sum(1 for c in counts.values() if c == i) for i in range(1, 5)]
        y = n[0] / (n[0] + 2 * n[1]) if n[0] + n[1] else 0.5
        d = [min(max((i + 1) - (i + 2) * y * n[i + 1] / n[i] if n[i] and n[i + 1] else 0.5 * (i + 1), 0.05), i + 0.95) for i in range(3)]
        total, spare = defaultdict(float), defaultdict(float)
        for g, c in counts.items():
            total[g >> 12] += c
            spare[g >> 12] += d[min(c, 3) - 1]
        for g, c in counts.items():
            out.setdefault((k << 60) | g, [0.0, 1.0])[0] = (c - d[min(c, 3) - 1]) / total[g >> 12]
        for h in total:
            out.setdefault(((k - 1) << 60) | h, [0.0, 1.0])[1] = spare[h] / total[h]
    return out


def test_model_equals_the_definition(spark):
    texts = ["the cat sat on the mat", "the dog sat on the log and the cat", "a bad cab", "the the the"]
    df = spark.createDataFrame([("en", t) for t in texts], "lang string, text string")
    table = quality_lm.model(quality_lm.count_grams(df), len(texts)).collect()
    want = plain_model(texts)
    # contexts are also grams, so weights of levels below are merged into their rows
    assert {r["key"] for r in table} == set(want)
    for r in table:
        assert r["share"] == pytest.approx(want[r["key"]][0], abs=1e-6)
        assert r["weight"] == pytest.approx(want[r["key"]][1], abs=1e-6)


def plain_perplexity(text, table, alphabet):
    """By the recursion on dictionaries, character by character."""
    import math

    g, _ = quality_lm.grams([text], alphabet)
    total = 0.0
    for full in g.tolist():
        p = 1 / (1 << quality_lm.BITS)
        for k in range(1, quality_lm.ORDER + 1):
            gram = full & ((1 << (12 * k)) - 1)
            share = table.get((k << 60) | gram, (0.0, 1.0))[0]
            weight = table.get(((k - 1) << 60) | (gram >> 12) if k > 1 else 0, (0.0, 1.0))[1]
            p = share + weight * p
        total += math.log2(p)
    return 2 ** (-total / len(g))


def test_perplexities_equal_the_definition(spark):
    texts = ["the cat sat on the mat", "日本語の文章です、そして漢字と仮名", "the dog sat on the log", "", None, "नमस्ते दुनिया the cat", "\U00010400 z " * 3_000]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, lang string")
    letters = quality_lm.alphabets(df)
    table = quality_lm.model(quality_lm.count_grams(df, letters=letters), len(texts))
    values = {r["key"]: (r["share"], r["weight"]) for r in table.collect()}
    got = {r["doc_id"]: r["perplexity"] for r in quality_lm.perplexities(df, table, letters=letters).collect()}
    assert got[3] is None and got[4] is None
    for i in (0, 1, 2, 5, 6):
        assert got[i] == pytest.approx(plain_perplexity(texts[i], values, letters["x"]), rel=1e-4)
    assert len(set(letters["x"][1].tolist())) == len({c for t in texts for c in t or ""})  # no two characters share a code


def test_classifier_frame(spark):
    good = ["the river ran by the old house and the birds sang in the trees near the water", "a house by the river is a fine place to hear the birds sing in the morning"]
    rows = [(i, good[i % 2] + f" {i}", "en") for i in range(80)] + [(200, "#$%& zqx @@ !! jjq " * 20, "en"), (201, None, "en"), (202, "  ", "en"), (203, "untrained words", "fr"), (204, "no language", None)]
    docs = spark.createDataFrame([(*r, 1.0) for r in rows], "doc_id long, text string, lang string, perplexity double")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(60)] + [(0, 1, 0), (200, 0, 0)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality_lm.classify(docs, labels).collect()}
    assert len(got) == len(rows)
    assert all(got[i]["kept"] for i in range(80))
    assert not got[200]["kept"] and got[200]["perplexity"] > got[200]["highest"]
    assert not got[201]["kept"] and not got[202]["kept"] and got[201]["perplexity"] is None
    assert got[203]["kept"] and got[203]["perplexity"] is None and got[204]["kept"] and got[204]["lang"] == "und"
    assert quality_lm.classify(docs.limit(0), labels).count() == 0
    assert quality_lm.classify(docs, labels.limit(0)).where("kept").count() == 83
