import hashlib

import pytest

public_tokenizers = pytest.importorskip("public_tokenizers")
tiktoken = pytest.importorskip("tiktoken")
tokenizers = pytest.importorskip("tokenizers")

from hypothesis import given, settings  # noqa: E402
from hypothesis import strategies as st  # noqa: E402

from graphwave.llm import bpe, token_count  # noqa: E402

PATH = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
PIECES = ["a", "b", "the", "s", "t", "re", "ve", "'", "'s", " ", "  ", "\n", "é", "日本", "1", "!?", "<|endoftext|>", "🙂", "\U0010ffff", "\x85", "\0", "token"]
TEXTS = st.lists(st.sampled_from(PIECES) | st.characters(exclude_categories=["Cs"]), max_size=40).map("".join)


@pytest.fixture(scope="module")
def ours():
    return bpe.Encoder(bpe.read_ranks(PATH), public_tokenizers.PATTERN)


@pytest.fixture(scope="module")
def library():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.parse_ranks(bpe.read_ranks(PATH)), special_tokens={})


@settings(max_examples=300, deadline=None)
@given(text=TEXTS)
def test_ids_equal_the_library(ours, library, text):
    ids = ours.encode(text)
    assert ids == library.encode_ordinary(text)
    assert ours.decode(ids) == text.encode()


@pytest.mark.parametrize("text", ["ab" * 30_000, "a" * 30_000, " " * 5_000, "\n" * 999, "日" * 4_000])
def test_long_pieces(ours, library, text):
    assert ours.encode(text) == library.encode_ordinary(text)


@pytest.fixture(scope="module")
def counter():
    return token_count.Counter(*token_count.read_merges(public_tokenizers.path("byte_bpe_50k.json")))


@pytest.fixture(scope="module")
def counting_library():
    return tokenizers.Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


@settings(max_examples=300, deadline=None)
@given(texts=st.lists(TEXTS, max_size=6))
def test_counts_equal_the_library(counter, counting_library, texts):
    assert counter.of(texts) == [len(x.ids) for x in counting_library.encode_batch(texts, add_special_tokens=False)]


def test_chunk_borders_do_not_matter(counter, counting_library):
    """Texts longer than a chunk, with apostrophes and blanks at every offset."""
    for shift in range(6):
        text = "x" * shift + "it's  we'll\n\n they've 12 " * 60
        assert counter.of([text]) == [len(counting_library.encode(text, add_special_tokens=False).ids)]


def test_long_pieces_by_chunks(counter, counting_library, monkeypatch):
    """Pieces far longer than a chunk: one letter over and over, random letters, hash signs, letters beyond the basic plane; and a table of states
    that is made anew in the middle of a piece."""
    import random

    r = random.Random(2)
    texts = ["a" * 30_000, "".join(r.choices("abcdefghijklmnopqrstuvwxyzé日", k=20_000)), "#" * 10_001, "thethe" * 3_000, "\U00010400\U00010401" * 3_000, "ab" * 1_024 + "x"]
    want = [len(counting_library.encode(t, add_special_tokens=False).ids) for t in texts]
    assert counter.of(texts) == want
    fresh = token_count.Transducer(counter.counts.transducer.merges)
    monkeypatch.setattr(fresh, "CHUNK", 64)
    monkeypatch.setattr(fresh, "WARM", 3)  # wrong guesses have to be mended
    monkeypatch.setattr(fresh, "MOST", 500)
    assert [fresh.count(t.encode()) for t in texts] == want and len(fresh.states) <= 502


def test_scan_of_partial_maps():
    maps = [{0: (1, 5)}, {1: (2, 7), 3: (0, 1)}, {9: (9, 9)}, {2: (0, 1)}]
    assert token_count.scanned(maps)[:2] == [{0: (1, 5)}, {0: (2, 12)}]
    assert token_count.scanned(maps)[2] == {} and token_count.scanned(maps)[3] == {}


def test_prefix_scan_composes_left_to_right():
    import numpy as np

    maps = np.random.default_rng(1).integers(0, 8, (37, 8)).astype(np.uint8)
    want, now = [], np.arange(8)
    for m in maps:
        now = m[now]
        want.append(now)
    assert (token_count.compose_scan(maps) == np.array(want)).all()


def test_frames(spark, library, counting_library):
    texts = [None, "", "It's a test", "It's a test", "long " * 9_000]
    df = spark.createDataFrame([(i, t, "x", 7) for i, t in enumerate(texts)], "doc_id long, text string, ids string, n_tokens int")
    got = {r[0]: tuple(r)[1:] for r in bpe.digests(bpe.encode(df, PATH, public_tokenizers.PATTERN)).collect()}
    for i, t in enumerate(texts):
        ids = library.encode_ordinary(t or "")
        assert got[i] == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())
    back = bpe.decode(bpe.encode(df, PATH, public_tokenizers.PATTERN).drop("decoded"), PATH)
    assert {r[0]: bytes(r[1]).decode() for r in back.collect()} == {i: t or "" for i, t in enumerate(texts)}
    rows = token_count.count_tokens(df, public_tokenizers.path("byte_bpe_50k.json")).collect()
    for r in rows:
        t = texts[r["doc_id"]] or ""
        n = len(counting_library.encode(t, add_special_tokens=False).ids)
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(t.encode()), n, n > 512)
    empty = df.limit(0)
    assert bpe.encode(empty, PATH, public_tokenizers.PATTERN).count() == 0 and token_count.count_tokens(empty, public_tokenizers.path("byte_bpe_50k.json")).count() == 0
