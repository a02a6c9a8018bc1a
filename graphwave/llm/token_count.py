"""Token counts from a tokenizer compiled to finite-state transducers.

Two transducers in a row. The first reads characters and marks where a piece begins. Its alphabet is a character's class with as
much of the following characters as the public pattern looks ahead, its states are what the character before was. It is run over
fixed-size chunks at once: every chunk is tabulated from every state, the chunk maps are composed by a parallel prefix scan, and
then each chunk is run from the state in which it really begins. So a text of any length is split across chunks, and the cost
does not depend on where texts begin. The second transducer reads the bytes of one piece. Its transitions carry how many tokens
the encoding of what was read so far grows or shrinks by; it is made deterministic lazily, state by state, from the tokens that
end at each place and which of them can follow which; a long piece is split into chunks, whose state maps are composed by a scan too. A state keeps the part of a token still open and the last tokens before
each place within it, with counts relative to the present. The map of a whole piece is remembered.

Null and empty texts have 0 bytes and 0 tokens. An added token's string inside a text counts as one token, as the library has it
by default. Repeated rows, ties and extra columns need no care: rows are mapped one by one.
"""

from __future__ import annotations

import json
import re
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, texts_of

# ---------------------------------------------------------------------------------------------------------------------
# pieces

LETTER, NUMBER, OTHER, BLANK, SPACE, STOP = range(6)  # BLANK: U+0020; SPACE: other white space; STOP: between texts
_CLASS: np.ndarray | None = None


def classes() -> np.ndarray:
    """Class of each code point, as \\p{L}, \\p{N} and \\s have it."""
    global _CLASS
    if _CLASS is None:
        of = {"L": LETTER, "N": NUMBER}
        table = np.fromiter((of.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x110000)), dtype=np.uint8, count=0x110000)
        table[[9, 10, 11, 12, 13, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]] = SPACE
        table[32] = BLANK
        _CLASS = table
    return _CLASS


#: What may follow an apostrophe at the start of a piece; fixed by the pattern.
TAILS = ("s", "t", "re", "ve", "m", "ll", "d")

# states: what was read last
_S_START, _S_LETTER, _S_NUMBER, _S_OTHER, _S_BLANK, _S_SPACE, _S_TAIL1, _S_TAIL2 = range(8)
# symbols: class, with the lookahead that matters
_Y_LETTER, _Y_NUMBER, _Y_OTHER, _Y_QUOTE1, _Y_QUOTE2, _Y_BLANK_IN, _Y_BLANK_LAST, _Y_SPACE_IN, _Y_SPACE_LAST, _Y_STOP = range(10)


def _machine() -> tuple[np.ndarray, np.ndarray]:
    """next[state, symbol] and begins[state, symbol]. _LAST: the last blank before something that isn't blank."""
    nxt, begins = np.zeros((8, 10), dtype=np.uint8), np.zeros((8, 10), dtype=np.uint8)
    kinds = {_Y_LETTER: _S_LETTER, _Y_NUMBER: _S_NUMBER, _Y_OTHER: _S_OTHER}
    for state in range(8):
        for symbol in range(10):
            if symbol == _Y_STOP:
                to, new = _S_START, 0
            elif state in (_S_TAIL1, _S_TAIL2):  # inside an apostrophe's tail
                to, new = (_S_START if state == _S_TAIL1 else _S_TAIL1), 0
            elif symbol in (_Y_QUOTE1, _Y_QUOTE2) and state not in (_S_OTHER, _S_BLANK):
                to, new = (_S_TAIL1 if symbol == _Y_QUOTE1 else _S_TAIL2), 1
            elif symbol in (_Y_BLANK_IN, _Y_BLANK_LAST, _Y_SPACE_IN, _Y_SPACE_LAST):
                last = symbol in (_Y_BLANK_LAST, _Y_SPACE_LAST)
                to = _S_BLANK if symbol == _Y_BLANK_LAST else _S_SPACE
                new = int(last or state != _S_SPACE)
            else:
                to = kinds.get(symbol, _S_OTHER)
                new = int(state not in (to, _S_BLANK))
            nxt[state, symbol], begins[state, symbol] = to, new
    return nxt, begins


_NEXT, _BEGINS = _machine()
CHUNK = 256


def symbols(codes: np.ndarray) -> np.ndarray:
    """codes: code points of texts, each followed by the code 0x110000 - 1 that stands between texts."""
    kind = classes()[codes]
    kind[codes == 0x10FFFF] = STOP
    after = np.concatenate((kind[1:], [STOP]))
    last = after <= OTHER
    y = np.array([_Y_LETTER, _Y_NUMBER, _Y_OTHER, _Y_BLANK_IN, _Y_SPACE_IN, _Y_STOP], dtype=np.uint8)[kind]
    white = (kind == BLANK) | (kind == SPACE)
    y[white & last] += 1
    quotes = np.flatnonzero(codes == 39)
    if len(quotes):
        padded = np.concatenate((codes, [0x10FFFF] * 2))
        a, b = padded[quotes + 1], padded[quotes + 2]
        for tail in TAILS:
            hit = a == ord(tail[0])
            if len(tail) == 2:
                hit &= b == ord(tail[1])
            y[quotes[hit]] = _Y_QUOTE1 if len(tail) == 1 else _Y_QUOTE2
    return y


def compose_scan(maps: np.ndarray) -> np.ndarray:
    """maps[i]: state to state. Inclusive prefix compositions, in log2(n) rounds over all chunks at once."""
    maps, step = maps.copy(), 1
    while step < len(maps):
        maps[step:] = np.take_along_axis(maps[step:], maps[:-step], axis=1)
        step *= 2
    return maps


def piece_starts(y: np.ndarray) -> np.ndarray:
    """Positions at which a piece begins, STOP positions excluded."""
    n = len(y)
    rows = -(-n // CHUNK)
    grid = np.full(rows * CHUNK, _Y_STOP, dtype=np.uint8)
    grid[:n] = y
    grid = np.ascontiguousarray(grid.reshape(rows, CHUNK).T)
    states = np.tile(np.arange(8, dtype=np.uint8), (rows, 1))
    flat_next, flat_begins = _NEXT.ravel(), _BEGINS.ravel()
    for column in grid:
        states = flat_next[states * np.uint8(10) + column[:, None]]
    ends = compose_scan(states)
    now = np.concatenate(([_S_START], ends[:-1, _S_START])).astype(np.uint8)
    begins = np.empty((CHUNK, rows), dtype=np.uint8)
    for i, column in enumerate(grid):
        at = now * np.uint8(10) + column
        begins[i] = flat_begins[at]
        now = flat_next[at]
    return np.flatnonzero(np.ascontiguousarray(begins.T).ravel()[:n])


# ---------------------------------------------------------------------------------------------------------------------
# tokens of a piece


class Merges:
    """The vocabulary as merges, and which two tokens can stand side by side."""

    def __init__(self, halves: dict[int, tuple[int, int] | None], spelled: dict[int, bytes]):
        self.halves, self.spelled = halves, spelled
        self.joined = {h: t for t, h in halves.items() if h is not None}
        # a merge's priority is its number; a byte has none
        self.when = {t: (-1 if h is None else i) for i, (t, h) in enumerate(halves.items())}
        self.by_bytes = {s: t for t, s in spelled.items()}
        self.open = {s[:i] for s in spelled.values() for i in range(1, len(s) + 1)}
        self.memo: dict[tuple[int, int], bool] = {}

    def adjacent(self, a: int, b: int) -> bool:
        key = (a, b)
        if key not in self.memo:
            self.memo[key] = self._adjacent(a, b)
        return self.memo[key]

    def _adjacent(self, a: int, b: int) -> bool:
        """No merge across the border may come before the merges that absorb either side of it. Those of a are done in the order
        of its right edge, those of b in the order of its left edge."""
        right, left = [a], [b]
        while (h := self.halves[right[-1]]) is not None:
            right.append(h[1])
        while (h := self.halves[left[-1]]) is not None:
            left.append(h[0])
        i, j = len(right) - 1, len(left) - 1
        while True:
            across = self.joined.get((right[i], left[j]))
            on_left = self.when[right[i - 1]] if i else None
            on_right = self.when[left[j - 1]] if j else None
            if across is not None:
                t = self.when[across]
                # equal pairs merge from left to right: one on the left comes first, one on the right last
                if (on_left is None or t < on_left) and (on_right is None or t <= on_right):
                    return False
            if on_left is None and on_right is None:
                return True
            if on_right is None or (on_left is not None and on_left <= on_right):
                i -= 1
            else:
                j -= 1


def read_merges(path: str) -> tuple[bytes, list[str]]:
    """The vocabulary file and its added tokens' strings."""
    with open(path, "rb") as f:
        raw = f.read()
    return raw, [x["content"] for x in json.loads(raw)["added_tokens"]]


def byte_letters() -> dict[str, int]:
    """The printable letter that the file format writes for each byte: itself where printable, else the next from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def parse_merges(raw: bytes) -> Merges:
    model = json.loads(raw)["model"]
    letters, vocab = byte_letters(), model["vocab"]
    spell = lambda s: bytes(letters[c] for c in s)
    halves: dict[int, tuple[int, int] | None] = {vocab[c]: None for c in letters if c in vocab}
    spelled = {vocab[c]: bytes([b]) for c, b in letters.items() if c in vocab}
    for pair in model["merges"]:
        a, b = pair.split(" ") if isinstance(pair, str) else pair
        if vocab[a + b] not in halves:
            halves[vocab[a + b]] = (vocab[a], vocab[b])
            spelled[vocab[a + b]] = spell(a + b)
    return Merges(halves, spelled)


class Transducer:
    """Bytes of a piece to the growth of its token count, one transition per byte, made as they are needed.

    A state is (open, trail): open is the longest end of what was read that begins some token, trail has for each place from
    open's start on to the present the last token before that place and the count there less the count now."""

    MOST = 250_000
    #: Bytes of a chunk of a long piece, bytes before it that tell its state, and chunk maps that are kept.
    CHUNK, WARM, KEPT = 2_048, 256, 2_000

    def __init__(self, merges: Merges):
        self.merges = merges
        self.maps: dict[bytes, dict] = {}
        self.first = (b"", ((-1, 0),))
        self.reset()

    def reset(self) -> None:
        self.ids: dict[tuple, int] = {}
        self.states: list[tuple] = []
        self.edges: dict[int, tuple[int, int]] = {}

    def _id(self, state: tuple) -> int:
        found = self.ids.get(state)
        if found is None:
            found = self.ids[state] = len(self.states)
            self.states.append(state)
        return found

    def _edge(self, state: int, byte: int) -> tuple[int, int]:
        opened, trail = self.states[state]
        read = opened + bytes([byte])
        tokens, adjacent = self.merges.by_bytes, self.merges.adjacent
        for i in range(len(read)):  # the token that ends here is the one that can follow what ends where it begins
            token = tokens.get(read[i:])
            if token is not None and (trail[i][0] < 0 or adjacent(trail[i][0], token)):
                grown = trail[i][1] + 1
                break
        else:
            raise ValueError("the vocabulary lacks a byte")
        keep = next(i for i in range(len(read) + 1) if read[i:] in self.merges.open or i == len(read))
        now = tuple([(t, c - grown) for t, c in trail[keep:]]) + ((token, 0),)
        return self._id((read[keep:], now)), grown

    def run(self, state: tuple, data: bytes) -> tuple[tuple, int]:
        """The state behind these bytes, and by how much the count has grown. The table of states is made anew when it is full, also in
        the middle of a piece."""
        at, total = self._id(state), 0
        edges = self.edges
        for byte in data:
            key = at << 8 | byte
            edge = edges.get(key)
            if edge is None:
                if len(self.states) > self.MOST:
                    state = self.states[at]
                    self.reset()
                    edges, at = self.edges, self._id(state)
                    key = at << 8 | byte
                edge = edges[key] = self._edge(at, byte)
            at = edge[0]
            total += edge[1]
        return self.states[at], total

    def count(self, piece: bytes) -> int:
        if len(piece) <= self.CHUNK:
            return self.run(self.first, piece)[1]
        return self._long(piece)

    def _long(self, piece: bytes) -> int:
        """A long piece by chunks. A chunk's map takes the states that it may begin in to the states it ends in and what the count grows by;
        it is tabulated from the state that the bytes right before it lead to, whatever came earlier. The maps are composed by a prefix scan;
        where the real state isn't among those tabulated, it is added and the scan goes on from there. Chunks of the same bytes share a map."""
        chunks = [piece[i : i + self.CHUNK] for i in range(0, len(piece), self.CHUNK)]
        maps = [self.maps.setdefault(c, {}) for c in chunks]
        for i, (c, m) in enumerate(zip(chunks, maps, strict=True)):
            entry = self.run(self.first, chunks[i - 1][-self.WARM :])[0] if i else self.first
            if entry not in m:
                m[entry] = self.run(entry, c)
        done, state, total = 0, self.first, 0
        while done < len(chunks):
            reached = 0
            for r in scanned(maps[done:]):
                if state not in r:
                    break
                reached += 1
                now = r[state]
            if not reached:
                maps[done][state] = self.run(state, chunks[done])
                continue
            state, total, done = now[0], total + now[1], done + reached
        if len(self.maps) > self.KEPT:
            self.maps = {}
        return total


def scanned(maps: list[dict]) -> list[dict]:
    """Inclusive prefix compositions of maps {state: (state, growth)}, in log2(n) rounds; a state without a way through is left out."""
    out, step = list(maps), 1
    while step < len(out):
        out = [m if i < step else {s: (m[t][0], n + m[t][1]) for s, (t, n) in out[i - step].items() if t in m} for i, m in enumerate(out)]
        step *= 2
    return out


class _Counts(dict):
    MOST, CHARS = 300_000, 48

    def __init__(self, transducer: Transducer):
        super().__init__()
        self.transducer = transducer

    def __missing__(self, piece: str) -> int:
        n = self.transducer.count(piece.encode("utf-8", "surrogatepass"))
        if len(piece) <= self.CHARS:
            if len(self) >= self.MOST:
                self.clear()
            self[piece] = n
        return n


class Counter:
    def __init__(self, raw: bytes, added: list[str]):
        self.counts = _Counts(Transducer(parse_merges(raw)))
        self.added = re.compile("|".join(map(re.escape, sorted(added, key=len, reverse=True)))) if added else None

    def of(self, texts: list[str]) -> list[int]:
        if not texts:
            return []
        total, parts, owner = [0] * len(texts), [], []
        for i, t in enumerate(texts):
            if self.added is not None and self.added.search(t):
                total[i] = len(self.added.findall(t))
                rest = self.added.split(t)
            else:
                rest = (t,)
            parts += rest
            owner += [i] * len(rest)
        joined = "\U0010ffff".join(parts) + "\U0010ffff"
        codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        stops = np.cumsum([len(p) + 1 for p in parts]) - 1
        y = symbols(codes)
        wild = (codes == 0x10FFFF).sum() != len(stops)
        if wild:  # a text has the code that stands between texts: it is no letter, number or space
            real = np.ones(len(codes), dtype=bool)
            real[stops] = False
            y[(codes == 0x10FFFF) & real] = _Y_OTHER
            white = np.isin(y, (_Y_BLANK_IN, _Y_SPACE_IN)) & np.concatenate((((codes == 0x10FFFF) & real)[1:], [False]))
            y[white] += 1
        begins = piece_starts(y)
        ends = np.minimum(np.concatenate((begins[1:], [len(codes)])), stops[np.searchsorted(stops, begins)])
        n = np.fromiter(map(self.counts.__getitem__, [joined[a:b] for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]), dtype=np.int64, count=len(begins))
        sums = np.concatenate(([0], np.cumsum(n)))
        cut = np.searchsorted(begins, np.concatenate(([0], stops)))
        for i, k in zip(owner, np.diff(sums[cut]).tolist(), strict=True):
            total[i] += k
        return total


_READY: dict[int, Counter] = {}


def counter(raw: bytes, added: list[str]) -> Counter:
    key = hash((raw, tuple(added)))
    if key not in _READY:
        _READY[key] = Counter(raw, added)
    return _READY[key]


def count_tokens(docs: DataFrame, path: str, limit: int = 512, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) of every row's whole text."""
    raw, added = read_merges(path)
    shared = docs.sparkSession.sparkContext.broadcast(raw)  # one vocabulary file, a few MB
    kind = dict(docs.dtypes)[id_column]

    def make():
        own = counter(shared.value, added)

        def run(batch):
            size = pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())
            return pa.RecordBatch.from_arrays([batch.column(0), size, pa.array(own.of(texts_of(batch.column(1))), pa.int64())], [id_column, "n_bytes", "n_tokens"])

        return run

    return arrow_map(docs.select(id_column, text), f"{id_column} {kind}, n_bytes long, n_tokens long", make).withColumn("over_limit", F.col("n_tokens") > limit)
