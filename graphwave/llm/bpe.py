"""Byte-level pair encoding by backtracking over longest dictionary matches, and its inverse.

A vocabulary file gives tokens and ranks. Bytes are mapped to Latin-1 characters, so that one Aho-Corasick automaton finds every
token that occurs in a piece. Merging is replayed without merging: take the longest token at each place, and go back to a
shorter one whenever it can't stand next to its left neighbour. Two tokens can stand together exactly if merging their joint
bytes leaves those two; this is remembered by pair. Every place is tried at most once per token, so a piece costs time in
proportion to its length. Pieces are what the public pattern matches, and each is encoded by itself.

Null and empty texts have no ids and decode to no bytes. Repeated rows, ties and extra columns need no care: rows are mapped one
by one and only the id and text columns are read. The automaton and the memos live in the worker process; the piece memo is
kept in two generations of bounded size.
"""

from __future__ import annotations

import base64
from array import array
from itertools import chain

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, texts_of

#: Pieces remembered by a worker in each of two generations, and the longest that is.
MEMO_PIECES, MEMO_CHARS = 180_000, 48
_READY: dict[tuple[int, int], Vocabulary] = {}


def read_ranks(path: str) -> bytes:
    """A rank file: lines of a base64 token and its rank. Under 1 MB for the usual 50,000 tokens."""
    with open(path, "rb") as f:
        return f.read()


def parse_ranks(raw: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in (line.split() for line in raw.splitlines() if line)}


def _halves(token: bytes, ranks: dict[bytes, int], rank: int) -> tuple[int, int] | None:
    """The two tokens whose merge yields this one, or None if merging its bytes never reaches it."""
    parts = [token[i : i + 1] for i in range(len(token))]
    while len(parts) > 2:
        best = min(((ranks.get(parts[i] + parts[i + 1], 1 << 60), i) for i in range(len(parts) - 1)))
        if best[0] >= rank:
            return None
        i = best[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
    return ranks[parts[0]], ranks[parts[1]]


class Vocabulary:
    def __init__(self, raw: bytes, whole_pieces: bool = True):
        """whole_pieces: a piece that is itself a token is that token, even if merging wouldn't reach it."""
        ranks = parse_ranks(raw)
        self.tokens: dict[int, bytes] = {r: t for t, r in ranks.items()}
        self.ranks = ranks
        self.whole = {t.decode("latin-1"): r for t, r in ranks.items()} if whole_pieces else {}
        self.parts: dict[int, tuple[int, int] | None] = {}
        self.merged: dict[tuple[int, int], int] = {}
        self.automaton = ahocorasick.Automaton()
        for token, rank in ranks.items():
            if len(token) == 1:
                self.parts[rank] = None
            elif (halves := _halves(token, ranks, rank)) is None:
                continue  # merging never yields it
            else:
                self.parts[rank] = halves
                self.merged[halves] = rank
            self.automaton.add_word(token.decode("latin-1"), (rank, len(token)))
        self.automaton.make_automaton()
        self.fits: dict[tuple[int, int], bool] = {}

    def compatible(self, left: int, right: int) -> bool:
        """Whether merging the bytes of both leaves exactly these two tokens."""
        key = (left, right)
        known = self.fits.get(key)
        if known is None:
            if len(self.fits) > 400_000:
                self.fits.clear()
            known = self.fits[key] = self._stand_together(left, right)
        return known

    def _stand_together(self, left: int, right: int) -> bool:
        """Walks the merges of both tokens backwards, latest first; a merge across the border that would have come before the
        one just undone means that the two don't stay apart."""
        limit = 1 << 60
        while True:
            across = self.merged.get((left, right))
            if across is not None and across < limit:
                return False
            # the younger of the two last merges is undone: of the left token its right half stays, of the right one its left half
            if left > right:
                limit = left
                halves = self.parts[left]
                if halves is not None:
                    left = halves[1]
                    continue
                limit, halves = right + 1, self.parts[right]
                if halves is None:
                    return True
                right = halves[0]
            else:
                limit = right + 1
                halves = self.parts[right]
                if halves is not None:
                    right = halves[0]
                    continue
                limit, halves = left, self.parts[left]
                if halves is None:
                    return True
                left = halves[1]

    def encode_piece(self, piece: str) -> tuple[int, ...]:
        """Ids of one piece, given as Latin-1 characters of its UTF-8 bytes."""
        rank = self.whole.get(piece)
        if rank is not None:
            return (rank,)
        n = len(piece)
        starts: list[list[tuple[int, int]]] = [[] for _ in range(n)]
        for end, token in self.automaton.iter(piece):
            starts[end - token[1] + 1].append(token)  # by rising end, so the longest comes last
        left = [len(s) - 1 for s in starts]  # the next candidate of each place
        dead = bytearray(n + 1)
        fits, compatible = self.fits, self.compatible
        path: list[tuple[int, int]] = []
        at = 0
        while at < n:
            taken = None
            options, k = starts[at], left[at]
            last = path[-1][0] if path else -1
            while k >= 0:
                rank, size = options[k]
                k -= 1
                if not dead[at + size]:
                    if last < 0:
                        taken = options[k + 1]
                        break
                    ok = fits.get((last, rank))
                    if ok if ok is not None else compatible(last, rank):
                        taken = options[k + 1]
                        break
            if taken is not None:
                left[at] = k
                path.append(taken)
                at += taken[1]
                if at < n:
                    left[at] = len(starts[at]) - 1
            else:
                if not path:
                    raise ValueError("the vocabulary lacks a byte")
                dead[at] = 1
                at -= path.pop()[1]
        return tuple([t[0] for t in path])


class _Pieces(dict):
    """Piece of text to ids, in two generations: when the young one is full it becomes the old one, and what is still used comes back from
    there, so frequent pieces stay."""

    def __init__(self, vocabulary: Vocabulary):
        super().__init__()
        self.vocabulary = vocabulary
        self.old: dict[str, tuple[int, ...]] = {}

    def __missing__(self, piece: str) -> tuple[int, ...]:
        ids = self.old.get(piece)
        if ids is None:
            ids = self.vocabulary.encode_piece(piece if piece.isascii() else piece.encode("utf-8", "surrogatepass").decode("latin-1"))
        if len(piece) <= MEMO_CHARS:
            if len(self) >= MEMO_PIECES:
                self.old = dict(self)
                self.clear()
            self[piece] = ids
        return ids


class Encoder:
    def __init__(self, raw: bytes, pattern: str):
        self.vocabulary = Vocabulary(raw)
        self.split = regex.compile(pattern).findall
        self.pieces = _Pieces(self.vocabulary)

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(map(self.pieces.__getitem__, self.split(text))))

    def decode(self, ids) -> bytes:
        return b"".join(map(self.vocabulary.tokens.__getitem__, ids))


def encoder(raw: bytes, pattern: str) -> Encoder:
    """One encoder per worker process and vocabulary."""
    key = (hash(raw), hash(pattern))
    if key not in _READY:
        _READY[key] = Encoder(raw, pattern)
    return _READY[key]


def _list_array(offsets: list[int], ids: array) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.frombuffer(ids, dtype=np.int32) if len(ids) else np.zeros(0, np.int32)))


def encode(docs: DataFrame, path: str, pattern: str, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, ids array<int>, decoded binary) of every row: the encoding of its whole text and what these ids decode to."""
    raw = docs.sparkSession.sparkContext.broadcast(read_ranks(path))
    kind = dict(docs.dtypes)[id_column]

    def make():
        own = encoder(raw.value, pattern)

        def run(batch):
            ids, offsets, back = array("i"), [0], []
            for text in texts_of(batch.column(1)):
                found = own.encode(text)
                ids.extend(found)
                offsets.append(len(ids))
                back.append(own.decode(found))
            return pa.RecordBatch.from_arrays([batch.column(0), _list_array(offsets, ids), pa.array(back, pa.binary())], [id_column, "ids", "decoded"])

        return run

    return arrow_map(docs.select(id_column, text), f"{id_column} {kind}, ids array<int>, decoded binary", make)


def decode(encoded: DataFrame, path: str, ids: str = "ids", id_column: str = "doc_id") -> DataFrame:
    """(id, decoded binary): the bytes of any table of id lists. A null list decodes to no bytes."""
    raw = encoded.sparkSession.sparkContext.broadcast(read_ranks(path))
    kind = dict(encoded.dtypes)[id_column]

    def make():
        tokens = {r: t for t, r in parse_ranks(raw.value).items()}

        def run(batch):
            back = [b"".join([tokens[i] for i in x or ()]) for x in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(back, pa.binary())], [id_column, "decoded"])

        return run

    return arrow_map(encoded.select(id_column, ids), f"{id_column} {kind}, decoded binary", make)


def digests(encoded: DataFrame, id_column: str = "doc_id") -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256) of what encode() returns."""
    return encoded.select(
        id_column,
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")).cast("binary"), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
