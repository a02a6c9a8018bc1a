import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from graphwave.functions.codecs import CODECS, Wah, decode_many, encode_many, huffman_codes, huffman_lengths, wah_count, wah_logical, wah_not


def sets(n):
    yield np.zeros(0, dtype=np.int64)
    yield np.arange(n)
    for i in {0, n - 1, n // 2, min(30, n - 1), min(31, n - 1)}:
        yield np.array([i])
    yield np.arange(0, n, 2)
    yield np.arange(n // 3, n)


@pytest.mark.parametrize("codec", sorted(CODECS))
@pytest.mark.parametrize("n", [1, 30, 31, 32, 94, 2125])
def test_round_trip(codec, n):
    encode, decode = CODECS[codec]
    for s in sets(n):
        assert decode(encode(s, n), n).tolist() == s.tolist()


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 500).flatmap(lambda n: st.tuples(st.just(n), st.sets(st.integers(0, n - 1)))))
def test_round_trip_any(case):
    n, members = case
    s = np.array(sorted(members), dtype=np.int64)
    for encode, decode in CODECS.values():
        assert decode(encode(s, n), n).tolist() == s.tolist()


def test_worked_example():
    """One set bit in sixteen, four-bit words, zero fills only."""
    assert Wah(4, zero_only=True).words(np.array([0]), 16) == [0b0100, 0b1100, 0b0000]


def test_long_fills_are_split():
    w = Wah(8)
    words = w.words(np.zeros(0, dtype=np.int64), 7 * 200)
    assert words == [0x80 | 63, 0x80 | 63, 0x80 | 63, 0x80 | 11]
    assert w.slots(words, 1400).tolist() == []


@settings(max_examples=60, deadline=None)
@given(st.sets(st.integers(0, 299)), st.sets(st.integers(0, 299)), st.sampled_from([8, 16, 32, 64]))
def test_logic_on_words(a, b, width):
    w, n = Wah(width), 300
    x, y = (w.words(np.array(sorted(s), dtype=np.int64), n) for s in (a, b))
    for op, want in (("and", a & b), ("or", a | b), ("andnot", a - b)):
        out = wah_logical(x, y, n, op, w)
        assert w.slots(out, n).tolist() == sorted(want)
        assert out == w.words(np.array(sorted(want), dtype=np.int64), n)
        assert wah_count(out, n, w) == len(want)
    assert w.slots(wah_not(x, n, w), n).tolist() == sorted(set(range(n)) - a)


def test_huffman_is_a_prefix_code():
    lengths = huffman_lengths({0: 50, 1: 20, 2: 20, 255: 10})
    assert lengths == {0: 1, 1: 3, 2: 2, 255: 3}  # 255 and 1 are merged first
    codes = list(huffman_codes(lengths).values())
    assert not any(a != b and b.startswith(a) for a in codes for b in codes)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 300).flatmap(lambda n: st.tuples(st.just(n), st.lists(st.sets(st.integers(0, n - 1)), max_size=6))), st.sampled_from(["wah", "wah8", "wah64", "bitmap", "varint"]))
def test_many_sets_at_once(case, codec):
    """Payloads of many sets are those of each set alone, and all members come back."""
    n, sets_ = case
    rows = [np.array(sorted(s), dtype=np.int64) for s in sets_]
    slots, ends = np.concatenate([*rows, np.zeros(0, np.int64)]), np.cumsum([0, *map(len, rows)])
    payloads = encode_many(codec, slots, ends, n)
    assert payloads == [CODECS[codec][0](r, n) for r in rows]
    which, found = decode_many(codec, payloads, [n] * len(rows))
    assert sorted(zip(which.tolist(), found.tolist(), strict=True)) == [(i, x) for i, r in enumerate(rows) for x in r.tolist()]
