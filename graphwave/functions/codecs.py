"""Byte lane of the frontier codecs: sorted slots to payload and back, vectorised.

A codec is a pair encode(slots, n_bits) -> bytes, decode(payload, n_bits) -> slots. The set lane in `sizes` computes the same sizes
from rows alone; tests hold the two against each other.
"""

from __future__ import annotations

import heapq
import zlib
from dataclasses import dataclass

import numpy as np

from .bits import pack_bitmap, to_bits, unpack_bitmap

# ---------------------------------------------------------------------------------------------------------------------
# word-aligned hybrid


@dataclass(frozen=True)
class Wah:
    """Words of `width` bits carry groups of width - 1 bits. A literal has top bit 0. A fill has top bit 1, then the fill's bit (unless
    only zeros are filled), then how many groups it covers. What doesn't fill a group stands in one active word at the end."""

    width: int = 32
    zero_only: bool = False

    @property
    def group(self) -> int:
        return self.width - 1

    @property
    def longest(self) -> int:
        return (1 << (self.width - (1 if self.zero_only else 2))) - 1

    def many(self, slots: np.ndarray, ends: np.ndarray, n_bits: int) -> tuple[np.ndarray, np.ndarray]:
        """The words of many sets of sorted slots, set i at ends[i] to ends[i + 1], and where each set's words end; in time proportional to
        the slots. Every set has its groups and one place behind them, at which its active word stands."""
        g, top, sets = self.group, np.uint64(1 << (self.width - 1)), len(ends) - 1
        full, rest = divmod(n_bits, g)
        slots = np.asarray(slots, dtype=np.int64)
        owner = np.repeat(np.arange(sets), np.diff(ends))
        place = slots % g
        inside = slots < full * g
        bit = np.uint64(1) << (np.where(inside, g, rest) - 1 - place).astype(np.uint64)
        grp = owner * (full + 1) + slots // g  # what is behind the last group falls on the set's last place
        first = np.flatnonzero(np.concatenate(([True], grp[1:] != grp[:-1]))) if len(grp) else np.zeros(0, np.int64)
        value = np.bitwise_or.reduceat(bit, first) if len(first) else np.zeros(0, np.uint64)
        held = grp[first]
        last = np.arange(sets) * (full + 1) + full
        bare = np.setdiff1d(last, held, assume_unique=True)
        at = np.concatenate((held, bare))
        order = np.argsort(at, kind="stable")
        at, value = at[order], np.concatenate((value, np.zeros(len(bare), np.uint64)))[order]
        active = at % (full + 1) == full
        ones = (value == np.uint64((1 << g) - 1)) & ~active & (not self.zero_only)
        gap = np.diff(np.concatenate(([-1], at))) - 1  # zero groups before each place
        begins = ones & ~(np.concatenate(([False], ones[:-1])) & (gap == 0))
        keep = begins | ~ones
        count = np.ones(len(at), np.int64)
        count[active] = rest > 0
        count[begins] = np.bincount((np.cumsum(begins) - 1)[ones], minlength=int(begins.sum()))
        kind = np.zeros(2 * int(keep.sum()), np.int64)  # 0: zero fill, 1: one fill, 2: literal
        n, val = np.empty_like(kind), np.zeros(len(kind), np.uint64)
        kind[1::2] = np.where(ones[keep], 1, 2)
        n[::2], n[1::2] = gap[keep], count[keep]
        val[1::2] = value[keep]
        times = np.where(kind == 2, n, -(-n // self.longest))
        total = np.cumsum(times)
        word_ends = np.concatenate(([0], total[1::2][active[keep]]))
        part = np.full(int(total[-1]) if len(total) else 0, self.longest, np.int64)
        some = times > 0
        part[total[some] - 1] = (n - (times - 1) * self.longest)[some]
        kind, val = np.repeat(kind, times), np.repeat(val, times)
        head = top | (np.uint64(0) if self.zero_only else (kind == 1).astype(np.uint64) << np.uint64(self.width - 2))
        return np.where(kind == 2, val, head | part.astype(np.uint64)).astype(np.uint64), word_ends

    def words(self, slots: np.ndarray, n_bits: int) -> list[int]:
        return self.many(slots, np.array([0, len(slots)]), n_bits)[0].tolist()

    def members(self, words: np.ndarray, ends: np.ndarray, n_bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(set, slot) of all members of many sets' words, in no order."""
        g = self.group
        words, n_bits = np.asarray(words, dtype=np.uint64), np.asarray(n_bits, dtype=np.int64)
        rest = n_bits % g
        tail = np.zeros(len(words), bool)
        tail[ends[1:][rest > 0] - 1] = True
        owner = np.repeat(np.arange(len(ends) - 1), np.diff(ends))
        fill = (words >> np.uint64(self.width - 1)).astype(bool) & ~tail
        groups = np.where(fill, words & np.uint64(self.longest), np.uint64(1)).astype(np.int64)
        groups[tail] = 0
        before = np.cumsum(groups) - groups
        at = before - before[ends[:-1][owner]] if len(words) else before
        one = fill & ((words >> np.uint64(self.width - 2) & np.uint64(1)).astype(bool) if not self.zero_only else False)
        n = groups[one] * g
        long_slots, long_owner = np.repeat(at[one] * g - (np.cumsum(n) - n), n) + np.arange(n.sum()), np.repeat(owner[one], n)
        plain = np.flatnonzero(~fill & (words != 0))
        shift = np.where(tail[plain], g - rest[owner[plain]], 0).astype(np.uint64)  # an active word's bits begin where a group's do
        row, place = np.nonzero(np.unpackbits((words[plain] << shift).astype(">u8").view(np.uint8)).reshape(-1, 64)[:, 64 - g :])
        return np.concatenate((long_owner, owner[plain][row])), np.concatenate((long_slots, at[plain][row] * g + place)).astype(np.int64)

    def slots(self, words, n_bits: int) -> np.ndarray:
        return np.sort(self.members(words, np.array([0, len(words)]), np.array([n_bits]))[1])

    def _type(self) -> str:
        return f">u{self.width // 8}"

    def encode(self, slots: np.ndarray, n_bits: int) -> bytes:
        return self.encode_many(slots, np.array([0, len(slots)]), n_bits)[0]

    def encode_many(self, slots: np.ndarray, ends: np.ndarray, n_bits: int) -> list[bytes]:
        words, at = self.many(slots, ends, n_bits)
        data, size = words.astype(self._type()).tobytes(), self.width // 8
        return [data[a * size : b * size] for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]

    def decode(self, payload: bytes, n_bits: int) -> np.ndarray:
        return self.slots(np.frombuffer(payload, dtype=self._type()), n_bits)

    def decode_many(self, payloads: list[bytes], n_bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ends = np.cumsum([0, *map(len, payloads)]) // (self.width // 8)
        return self.members(np.frombuffer(b"".join(payloads), dtype=self._type()), ends, n_bits)


def wah_logical(a: list[int], b: list[int], n_bits: int, op: str, wah: Wah) -> list[int]:
    """AND, OR or ANDNOT of two word lists, run by run, without expanding fills."""
    g, ones = wah.group, (1 << wah.group) - 1
    full, rest = divmod(n_bits, g)
    apply = {"and": lambda x, y: x & y, "or": lambda x, y: x | y, "andnot": lambda x, y: x & ~y & ones}[op]

    def runs(words):
        for w in words[:-1] if rest else words:
            if w >> (wah.width - 1):
                fill = 0 if wah.zero_only else w >> (wah.width - 2) & 1
                yield (ones if fill else 0), w & ((1 << (wah.width - (1 if wah.zero_only else 2))) - 1)
            else:
                yield w, 1

    out: list[tuple[int, int]] = []
    x, y = runs(a), runs(b)
    va = vb = na = nb = 0
    done = 0
    while done < full:
        if not na:
            va, na = next(x)
        if not nb:
            vb, nb = next(y)
        n = min(na, nb)
        v = apply(va, vb)
        if v in (0, ones) or n == 1:
            if out and out[-1][0] == v and v in (0, ones):
                out[-1] = (v, out[-1][1] + n)
            else:
                out.append((v, n))
        else:
            out += [(v, 1)] * n
        na, nb, done = na - n, nb - n, done + n
    words: list[int] = []
    for v, n in out:
        if v == 0 or (v == ones and not wah.zero_only):
            while n > 0:
                part = min(n, wah.longest)
                words.append(1 << (wah.width - 1) | (0 if wah.zero_only else (v != 0) << (wah.width - 2)) | part)
                n -= part
        else:
            words += [v] * n
    if rest:
        words.append(apply(a[-1], b[-1]) & ((1 << rest) - 1))
    return words


def wah_not(words: list[int], n_bits: int, wah: Wah) -> list[int]:
    g = wah.group
    full, rest = divmod(n_bits, g)
    everything = wah.words(np.arange(n_bits), n_bits)
    return wah_logical(everything, words, n_bits, "andnot", wah)


def wah_count(words: list[int], n_bits: int, wah: Wah) -> int:
    rest = n_bits % wah.group
    total = 0
    for w in words[:-1] if rest else words:
        if w >> (wah.width - 1):
            if not wah.zero_only and w >> (wah.width - 2) & 1:
                total += (w & ((1 << (wah.width - 2)) - 1)) * wah.group
        else:
            total += w.bit_count()
    return total + (words[-1].bit_count() if rest else 0)


# ---------------------------------------------------------------------------------------------------------------------
# the others


def sparse_encode(slots: np.ndarray, n_bits: int) -> bytes:
    return np.sort(slots).astype(">i8").tobytes()


def sparse_decode(payload: bytes, n_bits: int) -> np.ndarray:
    return np.frombuffer(payload, dtype=">i8").astype(np.int64)


def zlib_encode(level: int):
    return lambda slots, n_bits: zlib.compress(pack_bitmap(slots, n_bits), level)


def zlib_decode(payload: bytes, n_bits: int) -> np.ndarray:
    return unpack_bitmap(zlib.decompress(payload), n_bits)


def run_lengths(slots: np.ndarray, n_bits: int) -> np.ndarray:
    """Lengths of the maximal runs, the first of zeros (perhaps empty)."""
    bits = to_bits(slots, n_bits).astype(np.int8)
    edges = np.flatnonzero(np.diff(np.concatenate(([0], bits))))
    return np.diff(np.concatenate(([0], edges, [n_bits]))).astype(np.int64)


def rle_encode(slots: np.ndarray, n_bits: int) -> bytes:
    return run_lengths(slots, n_bits).astype(">u4").tobytes()


def rle_decode(payload: bytes, n_bits: int) -> np.ndarray:
    n = np.frombuffer(payload, dtype=">u4").astype(np.int64)
    return np.flatnonzero(np.repeat(np.arange(len(n)) % 2, n))


def varint_encode(slots: np.ndarray, n_bits: int) -> bytes:
    """Gaps between sorted slots, seven bits a byte, least significant first; the first gap is the slot itself."""
    gaps = np.diff(np.concatenate(([0], np.sort(slots)))).astype(np.uint64)
    parts = []
    for shift in range(0, 35, 7):
        live = (gaps >> np.uint64(shift) > 0) | (shift == 0)
        more = gaps >> np.uint64(shift + 7) > 0
        byte = (gaps >> np.uint64(shift) & np.uint64(127)).astype(np.uint8) | (more.astype(np.uint8) << 7)
        parts.append((live, byte))
    live = np.stack([p[0] for p in parts], axis=1)
    return np.stack([p[1] for p in parts], axis=1)[live].tobytes()


def varint_decode(payload: bytes, n_bits: int) -> np.ndarray:
    data = np.frombuffer(payload, dtype=np.uint8).astype(np.int64)
    if not len(data):
        return np.zeros(0, dtype=np.int64)
    last = data < 128
    owner = np.concatenate(([0], np.cumsum(last)[:-1]))
    first = np.flatnonzero(np.concatenate(([True], last[:-1])))
    place = np.arange(len(data)) - first[owner]
    return np.cumsum(np.bincount(owner, weights=(data & 127) << (7 * place)).astype(np.int64))


def huffman_lengths(frequencies: dict[int, int]) -> dict[int, int]:
    """Code lengths by byte value; ties go to the smaller value, then to what was merged earlier."""
    if len(frequencies) == 1:
        return dict.fromkeys(frequencies, 1)
    heap = [(n, i, (b,)) for i, (b, n) in enumerate(sorted(frequencies.items()))]
    heapq.heapify(heap)
    lengths, serial = dict.fromkeys(frequencies, 0), len(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for x in a[2] + b[2]:
            lengths[x] += 1
        heapq.heappush(heap, (a[0] + b[0], serial, a[2] + b[2]))
        serial += 1
    return lengths


def huffman_codes(lengths: dict[int, int]) -> dict[int, str]:
    """Canonical codes."""
    codes, code, before = {}, 0, 0
    for b, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        code <<= n - before
        codes[b] = f"{code:0{n}b}"
        code, before = code + 1, n
    return codes


def huffman_encode(slots: np.ndarray, n_bits: int) -> bytes:
    """256 code lengths, then the bitmap's bytes in canonical codes."""
    data = pack_bitmap(slots, n_bits)
    if not data:
        return b""
    values, counts = np.unique(np.frombuffer(data, dtype=np.uint8), return_counts=True)
    lengths = huffman_lengths(dict(zip(values.tolist(), counts.tolist(), strict=True)))
    codes = huffman_codes(lengths)
    bits = "".join([codes[b] for b in data])
    body = int("1" + bits, 2).to_bytes(len(bits) // 8 + 1, "big")
    return bytes(lengths.get(b, 0) for b in range(256)) + body


def huffman_decode(payload: bytes, n_bits: int) -> np.ndarray:
    if not payload:
        return np.zeros(0, dtype=np.int64)
    codes = {c: b for b, c in huffman_codes({b: n for b, n in enumerate(payload[:256]) if n}).items()}
    bits = bin(int.from_bytes(payload[256:], "big"))[3:]
    out, at, need = bytearray(), 0, -(-n_bits // 8)
    longest = max(map(len, codes))
    while len(out) < need:
        for k in range(1, longest + 1):
            b = codes.get(bits[at : at + k])
            if b is not None:
                out.append(b)
                at += k
                break
        else:
            raise ValueError("not a code")
    return unpack_bitmap(bytes(out), n_bits)


def bbc_encode(slots: np.ndarray, n_bits: int) -> bytes:
    """Byte-aligned runs: a head byte tells whether it stands for equal filler bytes (bit 7, with the filler bit in bit 6 and up to 63
    bytes) or is followed by up to 127 literal bytes."""
    data = np.frombuffer(pack_bitmap(slots, n_bits), dtype=np.uint8)
    out, i, n = bytearray(), 0, len(data)
    kind = np.where(data == 0, 0, np.where(data == 255, 1, 2))
    edges = [*(np.flatnonzero(np.diff(kind)) + 1).tolist(), n] if n else []
    for j in edges:
        k = kind[i]
        limit = 127 if k == 2 else 63
        while i < j:
            m = min(limit, j - i)
            if k == 2:
                out.append(m)
                out += data[i : i + m].tobytes()
            else:
                out.append(0x80 | int(k) << 6 | m)
            i += m
    return bytes(out)


def bbc_decode(payload: bytes, n_bits: int) -> np.ndarray:
    out, i = bytearray(), 0
    while i < len(payload):
        head = payload[i]
        i += 1
        if head & 0x80:
            out += (b"\xff" if head & 0x40 else b"\0") * (head & 0x3F)
        else:
            out += payload[i : i + head]
            i += head
    return unpack_bitmap(bytes(out), n_bits)


@dataclass(frozen=True)
class Plwah:
    """As the 32-bit word-aligned hybrid, but a zero fill may carry the place of one odd bit of the group behind it: five bits for the
    place (1-based, 0: none), 25 for the run."""

    def encode(self, slots: np.ndarray, n_bits: int) -> bytes:
        words, out = Wah(32).words(slots, n_bits), []
        rest = n_bits % 31
        body = words[:-1] if rest else words
        for w in body:
            single = w < 1 << 31 and w.bit_count() == 1
            if single and out and out[-1] >> 30 == 0b10 and not out[-1] >> 25 & 31:
                out[-1] |= (32 - w.bit_length()) << 25
            else:
                out.append(w)
        return b"".join(w.to_bytes(4, "big") for w in out + words[len(body) :])

    def decode(self, payload: bytes, n_bits: int) -> np.ndarray:
        words = [int.from_bytes(payload[i : i + 4], "big") for i in range(0, len(payload), 4)]
        rest, out = n_bits % 31, []
        for w in words[:-1] if rest else words:
            place = w >> 25 & 31 if w >> 30 == 0b10 else 0
            if place:
                out += [w & ~(31 << 25), 1 << (31 - place)]
            else:
                out.append(w)
        return Wah(32).slots(out + (words[-1:] if rest else []), n_bits)


CODECS = {
    "bitmap": (pack_bitmap, unpack_bitmap),
    "sparse": (sparse_encode, sparse_decode),
    **{f"wah{w}" if w != 32 else "wah": (Wah(w).encode, Wah(w).decode) for w in (8, 16, 32, 64)},
    **{f"zlib{k}": (zlib_encode(k), zlib_decode) for k in (0, 1, 6, 9)},
    "sparse_zlib": (lambda s, n: zlib.compress(sparse_encode(s, n), 1), lambda b, n: sparse_decode(zlib.decompress(b), n)),
    "rle": (rle_encode, rle_decode),
    "varint": (varint_encode, varint_decode),
    "huffman": (huffman_encode, huffman_decode),
    "bbc": (bbc_encode, bbc_decode),
    "plwah": (Plwah().encode, Plwah().decode),
}


def encode_many(codec: str, slots: np.ndarray, ends: np.ndarray, n_bits: int) -> list[bytes]:
    """The payloads of many sets of sorted slots, set i at ends[i] to ends[i + 1]."""
    encode = CODECS[codec][0]
    own = getattr(encode, "__self__", None)
    if isinstance(own, Wah):
        return own.encode_many(slots, ends, n_bits)
    return [encode(slots[a:b], n_bits) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]


def decode_many(codec: str, payloads: list[bytes], n_bits: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """(payload number, slot) of all members, in no order."""
    decode = CODECS[codec][1]
    own = getattr(decode, "__self__", None)
    if isinstance(own, Wah):
        return own.decode_many(payloads, np.array(n_bits))
    found = [decode(p, n) for p, n in zip(payloads, n_bits, strict=True)]
    return np.repeat(np.arange(len(found)), [len(x) for x in found]), np.concatenate(found) if found else np.zeros(0, np.int64)
