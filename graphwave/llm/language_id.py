"""Language identification by interpolated Kneser-Ney character models.

One model per language over letters (lower-cased, every run of non-letters is one blank). Four-letter windows of all languages
share one sorted array of hashes, whose rows hold each language's log-probability; windows that no language has seen are worked
out from the shorter ones. A text gets the language with the lowest cross-entropy per letter. A text is rejected if its lowest
cross-entropy lies above what held-back texts of that language show.

Null text, empty text and text without letters: `und`, score 0, rejected. A language needs one labelled row to be learned; with
none at all everything is `und`. Repeated rows are scored one by one and give the same answer; ties go to the language that
sorts first. Only the id and text columns are read when predicting.

What held-back texts show is taken per language and length: for each of a list of lengths, the cross-entropies of their first so
many letters have a high quantile, and the limit lies above it by a share of its distance from the median. Between two lengths
the limit is interpolated in 1 / sqrt(length). A text above its limit is judged once more by how many distinct windows it has.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, texts_of

ORDER = 4
UND = "und"
#: Lengths in letters at which held-back texts set a limit, and how many of them suffice. Longer texts are held to the last one:
#: what sets a text apart from others, such as its subject, doesn't average out.
LENGTHS = tuple(4 << i for i in range(7))
FEWEST = 30
_LETTER: np.ndarray | None = None


def _letters() -> np.ndarray:
    global _LETTER
    if _LETTER is None:
        _LETTER = np.fromiter((chr(c).isalpha() for c in range(0x110000)), dtype=bool, count=0x110000)
    return _LETTER


def _folded(codes: np.ndarray) -> np.ndarray:
    """16-bit codes of letters. Those beyond U+FFFF take the 8,192 codes from 0xD800 on, which no letter has; a script there is smaller than
    that, so its letters stay apart (but for the rarer ideographs)."""
    return np.where(codes > 0xFFFF, 0xD800 + (codes & 0x1FFF), codes)


def normalised(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Letters as 16-bit codes with single blanks between words, all texts in a row, and where each text begins. A text is
    led by ORDER - 1 blanks and closed by one; a text without letters has length 0."""
    pad = " " * ORDER
    joined = "".join(pad + t.lower() + " " for t in texts)
    sizes = np.array([len(t.lower()) + ORDER + 1 for t in texts], dtype=np.int64)
    codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    letter = _letters()[codes]
    before = np.concatenate(([True], letter[:-1]))
    ends = np.cumsum(sizes)
    starts = ends - sizes
    head = np.zeros(len(codes), dtype=bool)
    for j in range(1, ORDER):
        head[starts + j] = True
    keep = letter | before | head
    keep[starts] = False
    has = np.add.reduceat(letter, starts) > 0 if len(starts) else np.zeros(0, dtype=bool)
    if not has.all():
        keep &= np.repeat(has, sizes)
    kept = np.concatenate(([0], np.cumsum(keep)))
    out = np.where(letter, _folded(codes), 32)[keep].astype(np.uint64)
    return out, np.concatenate((kept[starts], kept[-1:]))


def windows(codes: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Packed ORDER-letter windows and where each text's windows begin."""
    n = len(codes)
    if n == 0:
        return np.zeros(0, dtype=np.uint64), np.zeros(len(at), dtype=np.int64)
    key = codes.copy()
    for j in range(1, ORDER):
        key[j:] |= codes[:-j] << np.uint64(16 * j)
    lead = np.zeros(n, dtype=bool)
    begins = at[:-1][np.diff(at) > 0]
    for j in range(ORDER - 1):
        lead[begins + j] = True
    sizes = np.maximum(np.diff(at) - (ORDER - 1), 0)
    return key[~lead], np.concatenate(([0], np.cumsum(sizes)))


def _hash(key: np.ndarray) -> np.ndarray:
    return key * np.uint64(0x9E3779B97F4A7C15)  # odd factor: one to one


def _find(table: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if len(table) == 0:
        return np.zeros(len(key), dtype=np.int64), np.zeros(len(key), dtype=bool)
    at = np.minimum(np.searchsorted(table, key), len(table) - 1)
    return at, table[at] == key


@dataclass
class Level:
    """One order of one language: discounted share of each gram, and the back-off weight of each context."""

    grams: np.ndarray
    share: np.ndarray
    contexts: np.ndarray
    weight: np.ndarray


def _level(grams: np.ndarray, counts: np.ndarray) -> Level:
    ones, twos = float((counts == 1).sum()), float((counts == 2).sum())
    discount = ones / (ones + 2 * twos) if ones and twos else 0.5
    contexts, back = np.unique(grams >> np.uint64(16), return_inverse=True)
    total = np.bincount(back, weights=counts)
    kinds = np.bincount(back)
    share = np.maximum(counts - discount, 0) / total[back]
    order = np.argsort(_hash(grams))
    by = np.argsort(_hash(contexts))
    return Level(_hash(grams)[order], share[order], _hash(contexts)[by], (discount * kinds / total)[by])


def _language(grams: np.ndarray, counts: np.ndarray) -> list[Level]:
    """Levels from ORDER down to 1: true counts on top, numbers of left neighbours below."""
    levels = [_level(grams, counts.astype(np.float64))]
    for k in range(ORDER - 1, 0, -1):
        grams, counts = np.unique(grams & np.uint64((1 << (16 * k)) - 1), return_counts=True)
        levels.append(_level(grams, counts.astype(np.float64)))
    return levels


def _resolve(levels: list[Level], keys: np.ndarray, letters: int) -> np.ndarray:
    """Probability of the last letter of each window given those before it, from the shortest history up."""
    p = np.full(len(keys), 1.0 / letters)
    for k, level in zip(range(1, ORDER + 1), reversed(levels), strict=True):
        gram = keys & np.uint64((1 << (16 * k)) - 1) if k < 4 else keys
        context = gram >> np.uint64(16)
        at, seen = _find(level.grams, _hash(gram))
        on, known = _find(level.contexts, _hash(context))
        p = np.where(seen, level.share[at], 0) + np.where(known, level.weight[on], 1.0) * p
    return p


@dataclass
class Model:
    languages: list[str]
    letters: int = 1
    levels: list[list[Level]] = field(default_factory=list)
    table: np.ndarray = field(default_factory=lambda: np.zeros(0, dtype=np.uint64))
    bits: np.ndarray = field(default_factory=lambda: np.zeros((0, 0), dtype=np.float32))
    #: By language, 1 / sqrt(length) ascending and the highest cross-entropy per letter at which a text of that length still counts.
    limit: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)

    def cross_entropy(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Bits per letter by text and language, and the number of letters."""
        keys, at = windows(*normalised(texts))
        n = np.diff(at)
        if len(keys) == 0:
            return np.zeros((len(texts), len(self.languages))), n
        row, seen = _find(self.table, _hash(keys))
        out = np.empty((len(texts), len(self.languages)))
        missing = np.flatnonzero(~seen)
        firsts = at[:-1][n > 0]
        for j in range(len(self.languages)):
            sums = np.zeros(len(texts))
            sums[n > 0] = np.add.reduceat(self._bits(j, keys, row, missing), firsts, dtype=np.float64)
            out[:, j] = sums / np.maximum(n, 1)
        return out, n

    def _bits(self, j: int, keys: np.ndarray, row: np.ndarray, missing: np.ndarray) -> np.ndarray:
        bits = self.bits[j][row]
        if len(missing):
            bits[missing] = -np.log2(_resolve(self.levels[j], keys[missing], self.letters))
        return bits

    def beginnings(self, texts: list[str], j: int) -> tuple[np.ndarray, np.ndarray]:
        """Language j's bits per letter over the first so many letters of each text, for all LENGTHS that the text reaches."""
        keys, at = windows(*normalised(texts))
        row, seen = _find(self.table, _hash(keys))
        sums = np.concatenate(([0.0], np.cumsum(self._bits(j, keys, row, np.flatnonzero(~seen)), dtype=np.float64)))
        n, start = np.diff(at), at[:-1]
        reach = [start[n >= k] for k in LENGTHS]
        return np.repeat(LENGTHS, [len(x) for x in reach]), np.concatenate([(sums[x + k] - sums[x]) / k for x, k in zip(reach, LENGTHS, strict=True)])

    def limits(self, best: np.ndarray, n: np.ndarray) -> np.ndarray:
        out = np.full(len(n), np.inf)
        for j, (at, bits) in enumerate(self.limit):
            mine = best == j
            if len(at):
                out[mine] = np.interp(1 / np.sqrt(np.maximum(n[mine], 1)), at, bits)
        return out

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """Language, score, cross-entropy and rejection of each text."""
        if not self.languages:
            z = np.zeros(len(texts))
            return [UND] * len(texts), z, z, np.ones(len(texts), dtype=bool)
        cost, n = self.cross_entropy(texts)
        best = cost.argmin(axis=1)
        low = cost[np.arange(len(texts)), best]
        score = 1.0 / np.exp2(-(cost - low[:, None]) * n[:, None]).sum(axis=1)
        score[n == 0] = 0
        reject = (n == 0) | (low > self.limits(best, n))
        for i in np.flatnonzero(reject & (n > 0)):  # a passage said again is no further evidence
            once = len(np.unique(windows(*normalised([texts[i]]))[0]))
            reject[i] = low[i] > self.limits(best[i : i + 1], np.array([once]))[0]
        return [self.languages[b] if k else UND for b, k in zip(best.tolist(), n.tolist(), strict=True)], score, low, reject


def build(counts: dict[str, tuple[np.ndarray, np.ndarray]]) -> Model:
    """A model from each language's distinct windows and how often each occurred."""
    languages = sorted(x for x in counts if len(counts[x][0]))
    if not languages:
        return Model([])
    union = np.unique(np.concatenate([counts[x][0] for x in languages]))
    letters = len(np.unique(union & np.uint64(0xFFFF))) + 1
    levels = [_language(*counts[x]) for x in languages]
    order = np.argsort(_hash(union))
    union = union[order]
    bits = np.stack([-np.log2(_resolve(lv, union, letters)) for lv in levels]).astype(np.float32)
    return Model(languages, letters, levels, _hash(union), bits)


def is_held_out(id_column: str = "doc_id"):
    """Rows kept from training: crc32 of the id as text has remainder 2 when divided by 4."""
    return F.coalesce(F.crc32(F.col(id_column).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, id_column: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = 600, calibrate: int = 200, quantile: float = 0.995, allowance: float = 0.5) -> Model:
    """Fits on a bounded sample of labelled rows that aren't held out: about `per_language` texts of each language for the
    counts and `calibrate` more for the rejection limits, drawn by a hash of the id. Whole texts are used. A limit is the `quantile` of the held-back texts at a length plus
    `allowance` times its distance from their median."""
    labelled = docs.where(F.col(lang).isNotNull() & F.col(text).isNotNull() & ~is_held_out(id_column))
    draw = F.pmod(F.xxhash64(F.col(id_column).cast("string"), F.lit("language sample")), F.lit(1 << 30)) / float(1 << 30)
    sizes = {r[0]: r[1] for r in labelled.groupBy(lang).count().collect()}
    if not sizes:
        return Model([])
    share = F.create_map(*[x for k, n in sizes.items() for x in (F.lit(k), F.lit((per_language + calibrate) / n))])
    aside = F.pmod(F.xxhash64(F.col(id_column).cast("string"), F.lit("calibration")), F.lit(per_language + calibrate)) < calibrate
    drawn = labelled.where(draw < share[F.col(lang)]).select(F.col(lang).alias("lang"), F.col(text).alias("text"), aside.alias("aside"))

    def count():
        def run(batch):
            keep = [not x for x in batch.column(2).to_pylist()]
            names, texts = batch.column(0).to_pylist(), texts_of(batch.column(1))
            out = {"lang": [], "gram": [], "n": []}
            for name in sorted(set(names)):
                keys, _ = windows(*normalised([t for t, x, k in zip(texts, names, keep, strict=True) if x == name and k]))
                grams, n = np.unique(keys, return_counts=True)
                out["lang"] += [name] * len(grams)
                out["gram"].append(grams.view(np.int64))
                out["n"].append(n.astype(np.int64))
            return pa.RecordBatch.from_arrays([pa.array(out["lang"], pa.string()), pa.array(np.concatenate(out["gram"])), pa.array(np.concatenate(out["n"]))], ["lang", "gram", "n"])

        return run

    grams = arrow_map(drawn, "lang string, gram long, n long", count).groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    found = grams.toArrow()
    names = found.column("lang").to_pylist()
    keys, n = np.asarray(found.column("gram")).view(np.uint64), np.asarray(found.column("n"))
    where = {k: i for i, k in enumerate(sorted(set(names)))}
    code = np.fromiter((where[x] for x in names), dtype=np.int64, count=len(names))
    counts = {}
    for k, i in where.items():
        mine = np.flatnonzero(code == i)
        order = mine[np.argsort(keys[mine])]
        counts[k] = keys[order], n[order]
    model = build(counts)
    if not model.languages:
        return model
    shared = docs.sparkSession.sparkContext.broadcast(model)  # as large as the sample's distinct windows

    def score():
        def run(batch):
            names, aside, texts = batch.column(0).to_pylist(), batch.column(2).to_pylist(), texts_of(batch.column(1))
            own, length, bits = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)], [np.zeros(0)]
            for j, name in enumerate(shared.value.languages):
                mine = [t for t, x, k in zip(texts, names, aside, strict=True) if x == name and k]
                if mine:
                    at, found = shared.value.beginnings(mine, j)
                    own.append(np.full(len(at), j))
                    length.append(at)
                    bits.append(found)
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (own, length, bits)], ["own", "length", "bits"])

        return run

    shown = arrow_map(drawn, "own long, length long, bits double", score).groupBy("own", "length").agg(F.count("*").alias("n"), F.percentile("bits", F.lit(0.5)).alias("middle"), F.percentile("bits", F.lit(quantile)).alias("high")).collect()
    shared.destroy()  # else the driver keeps it beside the finished model, for as long as something refers to it
    model.limit = _curves(len(model.languages), [(r["own"], r["length"], r["n"], r["high"] + allowance * (r["high"] - r["middle"])) for r in shown])
    return model


def _curves(languages: int, shown: list[tuple[int, int, int, float]]) -> list[tuple[np.ndarray, np.ndarray]]:
    """Limits by language from (language, length, texts, bits). A length that under FEWEST and under half of its
    texts reach is left out; a language without held-back texts gets the others' highest limits."""
    found: list[dict[int, float]] = [{} for _ in range(languages)]
    widest: dict[int, float] = {}
    most = {j: max(n for k, _, n, _ in shown if k == j) for j, *_ in shown}
    for j, length, n, bits in shown:
        if n >= min(FEWEST, most[j] / 2):
            found[j][length] = bits
            widest[length] = max(bits, widest.get(length, bits))
    curves = [sorted((1 / np.sqrt(k), v) for k, v in (x or widest).items()) for x in found]
    return [(np.array([a for a, _ in x]), np.array([b for _, b in x])) for x in curves]


def identify(docs: DataFrame, model: Model, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, lang_pred, score, bits, rejected) of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = dict(docs.dtypes)[id_column]

    def make():
        def run(batch):
            lang, score, bits, reject = shared.value.predict(texts_of(batch.column(1)))
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang, pa.string()), pa.array(score), pa.array(bits), pa.array(reject)], [id_column, "lang_pred", "score", "bits", "rejected"])

        return run

    return arrow_map(docs.select(id_column, text), f"{id_column} {kind}, lang_pred string, score double, bits double, rejected boolean", make)


def accepted(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """The rows that aren't rejected, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    column = docs.columns.index(text)

    def make():
        def run(batch):
            keep = ~shared.value.predict(texts_of(batch.column(column)))[3]
            return batch.filter(pa.array(keep))

        return run

    return arrow_map(docs, docs.schema, make, column)
