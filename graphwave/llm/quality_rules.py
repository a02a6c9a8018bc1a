"""Quality rules: plain counts, and how far a text's distributions lie from those of its language.

For every language the references are learned from all labelled rows of the input: how often each character class occurs, which words are
the most common ones, and how often each of these occurs (everything else is one bin). A text is compared with the language whose
references it is nearest to, by the Jensen-Shannon distance (base 2, so 0 to 1). A text is odd if one of its distances lies beyond the
limit of its language and length class; a limit is the median of the labelled rows that pass the base rules, plus SPREAD times what lies
between it and their 84 % point (a class of fewer than LEAST such rows takes its language's limit over all lengths). Texts below a minimum
length aren't judged by their distributions, since a short histogram is far from any reference by chance.

Null and empty texts have no words: counts 0, base_failed true, kept false. Without any labelled row there are no references and
the base rules decide alone. Repeated lines and words count as they stand; rows are mapped one by one, so repeated rows and
extra columns need no care. Equally common words: the first in byte order counts as common; equally near languages: the first by name.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_map, cut

#: The characters counted as symbols.
SYMBOLS = "#*$%&|<>"

#: Common words of a language, bytes that a common word has at most, and the rank up to which another language's common word is looked for.
TOP, LONGEST, DEEP = 40, 24, 400
#: Words and characters from which texts are judged by their distributions.
MIN_WORDS, MIN_CHARS = 60, 300
#: Bounds of the length classes, in words.
LENGTHS = (75, 100, 150, 200, 300, 500, 1000)
SPREAD, LEAST = 5.0, 30

#: Character classes: lower case, upper case, digits, blanks, line ends, sentence marks, other marks, symbols, everything else.
CLASSES = ("lower", "upper", "digit", "blank", "line", "sentence", "mark", "symbol", "rest")
_CLASS: np.ndarray | None = None


def _classes() -> np.ndarray:
    global _CLASS
    if _CLASS is None:
        table = np.full(0x110000, 8, dtype=np.uint8)
        for c in range(0x110000):
            x = chr(c)
            if x.isalpha():
                table[c] = 1 if x.isupper() else 0
            elif x.isdigit():
                table[c] = 2
            elif x.isspace():
                table[c] = 3
        table[[10, 13]] = 4
        table[[ord(x) for x in ".,;:?"]] = 5
        table[[ord(x) for x in "!\"'()-/[]{}_«»“”‘’–—¿¡…"]] = 6
        table[[ord(x) for x in SYMBOLS + "=+@^~\\`§"]] = 7
        _CLASS = table
    return _CLASS


def char_histograms(texts: list[str]) -> np.ndarray:
    codes = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    row = np.repeat(np.arange(len(texts)), [len(t) for t in texts])
    k = len(CLASSES)
    return np.bincount(row * k + _classes()[codes], minlength=len(texts) * k).reshape(len(texts), k).astype(np.float64)


def word_histogram(words: list[bytes], at: dict[bytes, int]) -> np.ndarray:
    """Counts of the common words by their places, and of all others."""
    out = np.zeros(len(at) + 1)
    for w in map(at.get, words):
        if w is not None:
            out[w] += 1
    out[-1] = len(words) - out[:-1].sum()
    return out


_STRIP = b".,;:?!\"'()#*$%&|<>"


def plain_words(words: list[bytes]) -> list[bytes]:
    """Words without the marks around them and in lower case."""
    return [w.strip(_STRIP).lower() for w in words]


def distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance between the rows of p and q, base 2; 1 where one of them is empty."""
    p, q = np.atleast_2d(p), np.atleast_2d(q)
    a, b = p.sum(axis=1, keepdims=True), q.sum(axis=1, keepdims=True)
    p, q = p / np.maximum(a, 1e-300), q / np.maximum(b, 1e-300)
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        left = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=1)
        right = np.where(q > 0, q * np.log2(q / m), 0).sum(axis=1)
    out = np.sqrt(np.clip((left + right) / 2, 0, 1))
    return np.where((a[:, 0] > 0) & (b[:, 0] > 0), out, 1.0)


@dataclass
class Counted:
    n_words: int
    word_chars: int
    n_symbols: int
    n_dup_lines: int
    n_repeat_words: int
    words: list[bytes]


def _repeated(words: list[bytes]) -> int:
    """Words that lie in a 3-word window found twice or more."""
    n = len(words)
    if n < 4:
        return 0
    seen: dict[bytes, int] = {}
    ids = np.array([seen.setdefault(w, len(seen)) for w in words], dtype=np.int64)
    if len(seen) < 1 << 21:
        key = ids[:-2] << 42 | ids[1:-1] << 21 | ids[2:]
    else:
        pairs: dict[tuple, int] = {}
        key = np.array([pairs.setdefault(x, len(pairs)) for x in zip(ids[:-2].tolist(), ids[1:-1].tolist(), ids[2:].tolist(), strict=True)])
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    if not same.any():
        return 0
    twice = np.zeros(len(key), dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(n, dtype=bool)
    covered[:-2] |= twice
    covered[1:-1] |= twice
    covered[2:] |= twice
    return int(covered.sum())


_SYMBOLS = SYMBOLS.encode()


def counted(text: str) -> Counted:
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()  # bytes split at blanks, tabs, line ends, vertical tabs and form feeds only
    inside = sum(map(len, words))
    if not text.isascii():
        inside -= len(raw) - len(text)  # continuation bytes; blanks have none
    symbols = sum(map(raw.count, _SYMBOLS))
    lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
    return Counted(len(words), inside, symbols, len(lines) - len(set(lines)), _repeated(words), words)


@dataclass
class References:
    languages: list[str]
    common: list[bytes]
    chars: np.ndarray
    words: np.ndarray


def fit(docs: DataFrame, text: str = "text", lang: str = "lang") -> References:
    """Histograms of every language over all labelled rows, in one pass: words and character classes are counted within slices, then
    across them; of each language, its most common words reach the driver."""
    k = len(CLASSES)

    def make():
        def run(batch):
            names = batch.column(0).to_pylist()
            texts = [x or "" for x in batch.column(1).to_pylist()]
            counts: dict[str, Counter] = {}
            totals: dict[str, np.ndarray] = {}
            for name, text, own in zip(names, texts, char_histograms(texts), strict=True):
                words = plain_words(text.encode("utf-8", "surrogatepass").split())
                counts.setdefault(name, Counter()).update(words)
                totals[name] = totals.get(name, 0) + np.append(own, len(words))
            rows = [(name, w, -1, n) for name, c in counts.items() for w, n in c.items() if 0 < len(w) <= LONGEST]
            rows += [(name, None, i, int(n)) for name, sums in totals.items() for i, n in enumerate(sums)]
            cols = list(zip(*rows, strict=True))
            return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.binary()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64())], ["lang", "word", "bin", "n"])

        return run

    rows = arrow_map(docs.where(F.col(lang).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("text")), "lang string, word binary, bin long, n long", make)
    counts = rows.groupBy("lang", "word", "bin").agg(F.sum("n").alias("n"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("bin"), F.desc("n"), "word"))  # the classes come first
    found = counts.withColumn("place", place).where(F.col("place") <= DEEP + k + 1).collect()  # so many rows a language
    languages = sorted({r["lang"] for r in found})
    common = sorted({bytes(r["word"]) for r in found if r["bin"] < 0 and r["place"] <= TOP + k + 1})
    at, place = {x: i for i, x in enumerate(languages)}, {w: i for i, w in enumerate(common)}
    chars, words = np.zeros((len(languages), k)), np.zeros((len(languages), len(common) + 1))
    for r in found:
        i = at[r["lang"]]
        if r["bin"] < 0:
            if bytes(r["word"]) in place:
                words[i, place[bytes(r["word"])]] = r["n"]
        elif r["bin"] < k:
            chars[i, r["bin"]] = r["n"]
        else:
            words[i, -1] = r["n"]
    words[:, -1] -= words[:, :-1].sum(axis=1)
    return References(languages, common, chars, words)


def measure(docs: DataFrame, references: References, id_column: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """One row per document: the counts, base_failed, the nearest language, the distances to its references, and whether the row is
    labelled."""
    shared = docs.sparkSession.sparkContext.broadcast(references)  # some tens of words and numbers a language
    kind = dict(docs.dtypes)[id_column]

    def make():
        ref = shared.value
        at = {w: i for i, w in enumerate(ref.common)}

        def run(batch):
            texts = [x or "" for x in batch.column(1).to_pylist()]
            rows = [counted(t) for t in texts]
            if ref.languages:
                chars = char_histograms(texts)
                words = np.stack([word_histogram(plain_words(c.words), at) for c in rows])
                by_char = np.stack([distance(chars, r) for r in ref.chars], axis=1)
                by_word = np.stack([distance(words, r) for r in ref.words], axis=1)
                near = (by_char + by_word).argmin(axis=1)
                i = np.arange(len(texts))
                char_d, word_d = by_char[i, near], by_word[i, near]
                nearest = [ref.languages[x] for x in near]
            else:
                char_d = word_d = np.zeros(len(texts))
                nearest = [None] * len(texts)
            n = np.array([c.n_words for c in rows], dtype=np.int64)
            repeat = np.array([c.n_repeat_words for c in rows], dtype=np.int64)
            failed = (n < 50) | (100 * repeat > 50 * n)
            return pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n)]
                + [pa.array([getattr(c, x) for c in rows], pa.int64()) for x in ("word_chars", "n_symbols", "n_dup_lines")]
                + [pa.array(repeat), pa.array(failed), pa.array(char_d), pa.array(word_d), pa.array(nearest, pa.string()), batch.column(2)],
                [id_column, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "char_distance", "word_distance", "nearest", "labelled"],
            )

        return run

    schema = f"{id_column} {kind}, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, char_distance double, word_distance double, nearest string, labelled boolean"
    return arrow_map(docs.select(id_column, text, F.col(lang).isNotNull().alias("labelled")), schema, make)


def length_class(n_words):
    return sum([(n_words >= x).cast("int") for x in LENGTHS], F.lit(0))


def limits(measured: DataFrame) -> DataFrame:
    """(nearest, length, char_limit, word_limit) of every language and length class that has labelled rows; a row each."""
    rows = measured.where("labelled and not base_failed and nearest is not null").where(_judged())
    rows = rows.select("nearest", length_class(F.col("n_words")).alias("length"), F.round("char_distance", 4).alias("c"), F.round("word_distance", 4).alias("w"))
    ends = [F.expr(f"percentile({x}, array(0.5, 0.84))").alias(x) for x in "cw"]  # of at most 10,000 different values
    found = rows.rollup("nearest", "length").agg(F.count("*").alias("n"), *ends).where("nearest is not null")
    beyond = lambda x: F.col(x)[0] + SPREAD * (F.col(x)[1] - F.col(x)[0])
    found = found.select("nearest", "length", "n", beyond("c").alias("char_limit"), beyond("w").alias("word_limit"))
    wide = found.where("length is null").select("nearest", F.col("char_limit").alias("c"), F.col("word_limit").alias("w"))
    own, classes = F.col("n") >= LEAST, F.explode(F.sequence(F.lit(0), F.lit(len(LENGTHS)))).alias("length")
    own_limits = found.where(F.col("length").isNotNull() & own).drop("n")
    return wide.select("nearest", classes, "c", "w").join(own_limits, ["nearest", "length"], "left").select("nearest", "length", F.coalesce("char_limit", "c").alias("char_limit"), F.coalesce("word_limit", "w").alias("word_limit"))


def _judged():
    return (F.col("n_words") >= MIN_WORDS) & (F.col("word_chars") >= MIN_CHARS)


def judge(docs: DataFrame, references: References | None = None, id_column: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """One row per document: the counts, base_failed, the distances to the nearest language, its limits, and kept. references: of another
    corpus; limits are always the input's own."""
    references = fit(docs, text, lang) if references is None else references
    measured = cut(measure(docs, references, id_column, text, lang))  # read twice: for the limits and for the verdicts
    bounds = cut(limits(measured).coalesce(1))  # a row per language and length class
    rows = measured.withColumn("length", length_class(F.col("n_words"))).join(F.broadcast(bounds), ["nearest", "length"], "left")
    odd = _judged() & ((F.col("char_distance") > F.col("char_limit")) | (F.col("word_distance") > F.col("word_limit")))
    counts = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]
    return rows.select(id_column, *counts, (~F.col("base_failed") & ~F.coalesce(odd, F.lit(False))).alias("kept"), "char_distance", "word_distance", "char_limit", "word_limit", "nearest")
