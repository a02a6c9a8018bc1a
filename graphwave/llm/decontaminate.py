"""Benchmark decontamination by SimHash over item-sized windows.

Words are lower-cased runs of letters and digits; shingles are five words, or all words of a shorter item. Every item, and every window of
every text that is as many words long as an item, gets a 64-bit SimHash of its shingles, weighted by how often each occurs. A multi-index
over four blocks of sixteen bits finds, for each window, the items whose fingerprint may lie within the radius: two fingerprints that differ
in at most r bits differ in at most r // 4 bits in some block, so tables of all block values within that distance miss none; the distance of
those is then worked out. Each pair within the radius is verified: first by how many of the window's shingles are any item's, which bounds
the similarity from above, then exactly, by the weighted Jaccard similarity of the two multisets of shingles.

Fingerprints are made of the windows in stretches of text that hold any item's shingle; everywhere else every window's similarity with every
item is 0, so this loses nothing. (Fingerprints of all windows of all lengths take 650 CPU seconds a GB, beyond what the check allows.)
A text shorter than an item is one window. An item of fewer than five words is a single shingle, whose fingerprint is its hash, and matches
equal shingles only.

The items are a stated query set: they are read in blocks of bounded size, and each block goes over all rows. Windows are worked out in
pieces of bounded size. Null and empty texts and items have no words and match nothing. Of several windows with one item, the one with the
highest similarity is reported, then the nearest fingerprint, then the first. Repeated rows are reported once per row.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, arrow_map, cut, shingles, texts_of

SHINGLE, SIMILARITY, RADIUS = 5, 0.8, 23
#: Bytes of benchmark text that go over the rows at once.
BLOCK_BYTES = 8 << 20
#: Windows that are worked out at once, and items that one index holds (a bit each).
PIECE, GROUP = 4_096, 64
_BLOCKS = 4


def bit_sums(hashes: np.ndarray, kind=np.int32) -> np.ndarray:
    """Row i: for each of 64 bits, how many of the first i hashes have it set less how many don't."""
    bits = np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").view(np.int8)
    sums = np.zeros((len(hashes) + 1, 64), dtype=kind)
    np.cumsum(2 * bits - 1, axis=0, out=sums[1:], dtype=kind)
    return sums


def fingerprints(sums: np.ndarray) -> np.ndarray:
    return np.packbits((sums > 0).ravel(), bitorder="little").view("<u8")


class Windows:
    """Fingerprints of windows from two rows of sums, in memory that is used again."""

    def __init__(self, most: int):
        self.bits = np.empty((most, 64), dtype=bool)

    def prints(self, ends: np.ndarray, begins: np.ndarray) -> np.ndarray:
        bits = self.bits[: len(ends)]
        np.greater(ends, begins, out=bits)
        return np.packbits(bits.ravel(), bitorder="little").view("<u8")


_NEAR = np.bitwise_count(np.arange(1 << 16, dtype=np.uint16))


class Index:
    """Fingerprints of up to GROUP items; for every block and block value, the items that differ from it in at most radius // 4 bits."""

    def __init__(self, prints: np.ndarray, radius: int):
        self.prints, self.radius = prints, radius
        kind = next(t for t, n in ((np.uint8, 8), (np.uint16, 16), (np.uint32, 32), (np.uint64, 64)) if len(prints) <= n)
        values = np.arange(1 << 16, dtype=np.uint16)
        blocks = prints.astype("<u8").view(np.uint16).reshape(-1, _BLOCKS)
        self.table = np.zeros((_BLOCKS, 1 << 16), dtype=kind)
        for i, own in enumerate(blocks):
            for b in range(_BLOCKS):
                self.table[b] |= (_NEAR[values ^ own[b]] <= radius // _BLOCKS).astype(kind) << kind(i)

    def within(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Every (window, item, distance) within the radius."""
        parts = windows.view("<u2").reshape(-1, _BLOCKS)
        maybe = self.table[0].take(parts[:, 0])
        for b in range(1, _BLOCKS):
            maybe |= self.table[b].take(parts[:, b])
        own = np.flatnonzero(maybe)
        if 4 * len(own) > 3 * len(windows):  # nearly all
            own = np.arange(len(windows))
        apart = np.bitwise_count(windows[None, own] ^ self.prints[:, None])
        i, w = np.divmod(np.flatnonzero(apart.ravel() <= self.radius), max(1, len(own)))
        return own[w], i, apart[i, w]


def weighted_jaccard(a: Counter, b: Counter) -> float:
    if len(a) > len(b):
        a, b = b, a
    both = sum(min(n, b[x]) for x, n in a.items() if x in b)
    return both / (sum(a.values()) + sum(b.values()) - both)


class Items:
    def __init__(self, ids: list, texts: list[str], radius: int = RADIUS, similarity: float = SIMILARITY):
        self.radius, self.similarity = radius, similarity
        words = Words(texts, letters_only=True)
        hashes, rows, _ = shingles(words, SHINGLE)
        cut_at = np.searchsorted(rows, np.arange(len(texts) + 1))
        members: dict[int, list[int]] = {}
        for i, n in enumerate(words.count.tolist()):
            if n:
                members.setdefault(n, []).append(i)
        self.groups: list[tuple[int, list, list[Counter], Index]] = []  # shingles of the items: ids, multisets, index
        self.short: dict[int, tuple[np.ndarray, dict[int, list]]] = {}
        known = []
        for n, who in sorted(members.items()):
            own = [hashes[cut_at[i] : cut_at[i + 1]] for i in who]
            if n < SHINGLE:
                by: dict[int, list] = {}
                for i, h in zip(who, own, strict=True):
                    by.setdefault(int(h[0]), []).append(ids[i])
                self.short[n] = np.array(sorted(by), dtype=np.uint64), by
                continue
            known += own
            prints = np.concatenate([fingerprints(bit_sums(h)[-1:]) for h in own])
            for a in range(0, len(who), GROUP):
                part = slice(a, a + GROUP)
                self.groups.append((n - SHINGLE + 1, [ids[i] for i in who[part]], [Counter(h.tolist()) for h in own[part]], Index(prints[part], radius)))
        self.known = np.unique(np.concatenate(known)) if known else np.zeros(0, np.uint64)
        self.longest = max((g[0] for g in self.groups), default=0)

    def _known(self, hashes: np.ndarray) -> np.ndarray:
        """Which hashes are some item's."""
        at = np.minimum(np.searchsorted(self.known, hashes), len(self.known) - 1)
        return self.known[at] == hashes

    def _verify(self, found: dict, group: tuple, hashes: np.ndarray, known: np.ndarray, starts: np.ndarray, stops: np.ndarray, row: np.ndarray, word: np.ndarray, near: tuple) -> None:
        """Exact similarity of the pairs (window, item, distance) in `near`; windows are starts to stops of the hashes, and begin at these
        words of these rows. known: how many hashes before each place are some item's."""
        span, ids, bags, _ = group
        w, i, apart = near
        size = stops[w] - starts[w]
        # the multisets share at most the window's shingles that are some item's
        both = known[stops[w]] - known[starts[w]]
        keep = np.flatnonzero(both >= self.similarity * (size + span - both) - 1e-9)
        w, i, apart = w[keep], i[keep], apart[keep]
        for k in np.lexsort((starts[w], apart)).tolist():
            item, a, b = int(i[k]), int(starts[w[k]]), int(stops[w[k]])
            best = found.setdefault(int(row[w[k]]), {})
            old = best.get(ids[item])
            if old is not None and old[0] == 1.0:
                continue
            s = weighted_jaccard(Counter(hashes[a:b].tolist()), bags[item])
            if s >= self.similarity and (old is None or (-s, int(apart[k]), a) < (-old[0], old[1], old[2])):
                best[ids[item]] = (s, int(apart[k]), a, int(word[w[k]]))

    def _stretches(self, found: dict, hashes: np.ndarray, rows: np.ndarray, place: np.ndarray, word: np.ndarray, real: np.ndarray) -> None:
        """All windows of all item lengths in stretches of shingles, given where they stand; a stretch ends with its row or where places aren't
        consecutive."""
        n_all = len(hashes)
        if not n_all:
            return
        ends = np.append(np.flatnonzero((np.diff(place) > 1) | (np.diff(rows) > 0)) + 1, n_all)
        last = np.repeat(ends, np.diff(np.concatenate(([0], ends))))
        known = np.concatenate(([0], np.cumsum(real)))
        kind = np.int16 if PIECE + self.longest < 30_000 else np.int32
        windows = Windows(min(PIECE, n_all))
        for lo in range(0, n_all, PIECE):
            hi = min(lo + PIECE, n_all)
            sums = bit_sums(hashes[lo : hi + self.longest], kind)
            for group in self.groups:
                n = min(hi, n_all - group[0] + 1) - lo
                if n > 0:
                    w, i, apart = group[3].within(windows.prints(sums[group[0] : group[0] + n], sums[:n]))
                    inside = np.flatnonzero(lo + w + group[0] <= last[lo + w])
                    if len(inside):
                        at = np.arange(lo, lo + n)
                        self._verify(found, group, hashes, known, at, at + group[0], rows[lo : lo + n], word[lo : lo + n], (w[inside], i[inside], apart[inside]))

    def search(self, texts: list[str]) -> list[tuple[int, object, int, int, float]]:
        """(row, item id, first word, distance, similarity) of every row and item that match."""
        words = Words(texts, letters_only=True)
        found: dict[int, dict] = {}
        if self.groups:
            hashes, rows, _ = shingles(words, SHINGLE)
            first = np.searchsorted(rows, np.arange(len(texts) + 1))
            real = self._known(hashes)
            known = np.concatenate(([0], np.cumsum(real)))
            place = np.arange(len(hashes))
            near = np.flatnonzero(known[np.minimum(place + self.longest, len(hashes))] > known[np.maximum(place - self.longest + 1, 0)])
            self._stretches(found, hashes[near], rows[near], near, (near - first[rows[near]]), real[near])
            count = np.diff(first)
            small = np.flatnonzero((known[first[1:]] > known[first[:-1]]) & (count < self.longest))  # rows that some item is longer than
            for lo in range(0, len(small), 512):
                own = small[lo : lo + 512]
                prints = np.concatenate([fingerprints(bit_sums(hashes[first[r] : first[r + 1]])[-1:]) for r in own.tolist()])
                for group in self.groups:
                    less = np.flatnonzero((count[own] < group[0]) & (count[own] >= self.similarity * group[0]))
                    if len(less):
                        r = own[less]
                        self._verify(found, group, hashes, known, first[r], first[r + 1], r, np.zeros(len(r), np.int64), group[3].within(prints[less]))
        for n, (values, by) in self.short.items():
            hashes, rows, at = shingles(words, n)
            for k in np.flatnonzero((words.count[rows] >= n) & np.isin(hashes, values)).tolist():
                for item in by[int(hashes[k])]:
                    found.setdefault(int(rows[k]), {}).setdefault(item, (1.0, 0, k, int(at[k])))
        out = []
        for row in sorted(found):
            out += [(row, item, start, apart, s) for item, (s, apart, _, start) in found[row].items()]
        return out


def item_blocks(benchmark: DataFrame, id_column: str = "item_id", text: str = "text", most: int = BLOCK_BYTES) -> Iterator[list[tuple]]:
    """The query set in blocks of about `most` bytes (or one item), one after the other. How many blocks there are follows from a
    distributed sum."""
    items = benchmark.where(F.length(F.trim(F.col(text))) > 0)
    total = items.agg(F.sum(F.octet_length(text))).first()[0] or 0
    n = max(1, -(-int(total) // most))
    for k in range(n):
        own = items if n == 1 else items.where(F.pmod(F.xxhash64(id_column), F.lit(n)) == k)
        block = [tuple(r) for r in own.select(id_column, text).collect()]
        if block:
            yield block


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_column: str = "doc_id", text: str = "text", item_column: str = "item_id", item_text: str = "text", radius: int = RADIUS, similarity: float = SIMILARITY, most: int = BLOCK_BYTES) -> DataFrame:
    """(id, item id, first_word, hamming, similarity) of every text and item of which the text holds a passage. What one block finds is
    written before the next is read, so the driver holds one block."""
    kind, item_kind = dict(docs.dtypes)[id_column], dict(benchmark.dtypes)[item_column]
    schema = f"`{id_column}` {kind}, `{item_column}` {item_kind}, first_word long, hamming long, similarity double"
    item_type = benchmark.select(item_column).limit(0).toArrow().schema.field(0).type
    names = [id_column, item_column, "first_word", "hamming", "similarity"]
    parts = []
    for block in item_blocks(benchmark, item_column, item_text, most):
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def make(shared=shared):
            items = Items([b[0] for b in shared.value], [b[1] for b in shared.value], radius, similarity)

            def run(batch):
                rows = items.search(texts_of(batch.column(1)))
                cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
                return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(cols[0], pa.int64())), pa.array(cols[1], item_type), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64()), pa.array(cols[4], pa.float64())], names)

            return run

        parts.append(cut(arrow_map(docs.select(id_column, text), schema, make)))
        shared.unpersist()
    if not parts:
        return docs.sparkSession.createDataFrame([], schema)
    return reduce(DataFrame.unionByName, parts)


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_column: str = "item_id", item_text: str = "text", radius: int = RADIUS, similarity: float = SIMILARITY, most: int = BLOCK_BYTES) -> DataFrame:
    """The rows that hold no passage of any item, with all their columns. Blocks of items are passed one after another; between two blocks
    the rows that are left are written."""
    column, before = docs.columns.index(text), None
    for block in item_blocks(benchmark, item_column, item_text, most):
        docs = docs if before is None else cut(docs)
        if before is not None:
            before.unpersist()
        before = shared = docs.sparkSession.sparkContext.broadcast(block)

        def make(shared=shared):
            items = Items([b[0] for b in shared.value], [b[1] for b in shared.value], radius, similarity)

            def run(batch):
                bad = {r[0] for r in items.search(texts_of(batch.column(column)))}
                return batch.filter(pa.array([i not in bad for i in range(batch.num_rows)]))

            return run

        docs = arrow_map(docs, docs.schema, make, column)
    return docs
