"""Personal data: detection and keyed surrogates.

Detected are e-mail addresses, IPv4 and IPv6 addresses, hardware addresses, payment cards (with a valid check digit), account
numbers (IBAN), phone numbers, identity numbers, secrets (keys, tokens, passwords) and personal names: capitalised words behind a
title or a phrase that introduces a person, with a known given name, or with an e-mail address of that name close behind. An entity is
a kind and a canonical form: lower case for what is written in letters, letters and digits only where separators vary. A name is made
of entities of its own, a given name and family names, so a person is the same one under "Ms Smith" and "Jane Smith".

An entity's surrogate follows from the caller's key, its kind and canonical form and how often it was drawn, so every mention in every
text gets the same one, and it keeps the format: length, character classes, signs, country codes and valid check digits; names keep
gender (of a known name, or told by a title anywhere in the corpus) and script.

Surrogates are checked across the corpus: no two entities of a kind may share one, and, given names apart, none may be a form that
occurs itself. Those that clash are drawn again, until none clash. Where a format leaves nothing to change, or so little that eight draws
have clashed, the surrogate outgrows it by ever more letters or digits, so drawing always ends. The lists of entities and clashes
stay distributed; the clashes are broadcast if they are few, and joined by a digest of the text otherwise, with the same result.

Null texts stay null and empty ones empty; ids are neither read nor needed. Overlapping findings: the one that begins first wins, then
the longer. Rows are mapped one by one, so repeated rows stay repeated. Where a column of the input is named as one of the result's own,
the result's gets underscores behind its name.
"""

from __future__ import annotations

import hashlib
import hmac
import re
import secrets

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import arrow_map, compact, cut

#: The session's setting that holds the key of the registered queries.
KEY_SETTING = "spark.graphwave.surrogates.key"
#: Clashing entities that are broadcast at most; beyond it they are joined by document.
BROADCAST_ROWS = 50_000

# ---------------------------------------------------------------------------------------------------------------------
# detection

_DIGITS = re.compile(r"(?<![\w.+(])[+(]{0,2}\d[\d .()\-/]{5,}\d(?!\w)")
_IPV4 = re.compile(r"(?<![\d.])(?:\d{1,3}\.){3}\d{1,3}(?!\d|\.\d)")
_CARD = re.compile(r"(?<![\d-])(?:\d{13,19}|\d{4}(?:[ -]\d{4}){2}[ -]\d{1,7}|\d{4}[ -]\d{6}[ -]\d{5})(?![\d-])")
_SSN = re.compile(r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])")
_PHONE = re.compile(r"(?<![\w+])(?:\+\d{1,3}[ .\-/]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .\-/]?\d{2,4}){1,4}|\(\d{3}\) ?\d{3}[ .\-]\d{4}|\d{3}[ .\-]\d{3}[ .\-]\d{4}|0\d{2,4}[ /\-]\d{5,8})(?!\d)")
_LOCAL = re.compile(r"[\w.%+\-]+\Z")
_DOMAIN = re.compile(r"[A-Za-z0-9\-]+(?:\.[A-Za-z0-9\-]+)+")
_ASSIGNED = re.compile(r"[=:]\s*[\"']?([A-Za-z0-9+/_\-.=~]{8,})")
_KEYWORD = re.compile(r"(?:token|secret|passw(?:or)?d|pwd|api[_\-]?key|access[_\-]?key|private[_\-]?key|auth(?:orization)?|bearer|credential)s?[\"']?\s*\Z", re.IGNORECASE)
_HEX = re.compile(r"(?<![0-9A-Za-z])[0-9a-fA-F]{32,128}(?![0-9A-Za-z])")
_MARKED = (
    ("AKIA", re.compile(r"\bAKIA[0-9A-Z]{16}\b")),
    ("gh", re.compile(r"\bgh[pousr]_[A-Za-z0-9]{36,}\b")),
    ("sk-", re.compile(r"\bsk-[A-Za-z0-9_\-]{20,}")),
    ("xox", re.compile(r"\bxox[abprs]-[A-Za-z0-9\-]{10,}")),
    ("eyJ", re.compile(r"\beyJ[\w\-]{8,}\.[\w\-]{8,}\.[\w\-]{4,}")),
    ("PRIVATE KEY-----", re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----.*?-----END [A-Z ]*PRIVATE KEY-----", re.DOTALL)),
)
_IBAN = re.compile(r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b")
_MAC = re.compile(r"(?<![0-9A-Fa-f:\-])(?:[0-9A-Fa-f]{2}([:\-]))(?:[0-9A-Fa-f]{2}\1){4}[0-9A-Fa-f]{2}(?![0-9A-Fa-f:\-])")
_IPV6 = re.compile(r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])|(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){2,6}:[0-9A-Fa-f]{1,4}(?::[0-9A-Fa-f]{1,4}){0,4}(?![0-9A-Fa-f:])")
_UP = "A-ZÀ-ÖØ-ÞŁŚŠŽÇА-ЯЁΑ-Ω"
_CAPITALS = re.compile(rf"(?<!\w)[{_UP}][\w'’]*\.?[ ]+[{_UP}][\w'’\-]+(?:[ ]+[{_UP}][\w'’\-]+)?")

#: What stands right before a person's name.
_CUE = re.compile(
    r"(?:my name is|name:|signed(?: by)?[,:]?|(?:kind |best |warm )?regards,|sincerely,|yours truly,|author:|attn:?|contact:|ich heiße|mein name ist|"
    r"mit freundlichen grüßen,?|je m['’]appelle|cordialement,|me llamo|mi nombre es|atentamente,|меня зовут|με λένε)\s*\Z",
    re.IGNORECASE,
)
_MAILBOX = re.compile(r"[\w.%+\-]+(?=@[A-Za-z0-9])")


def _own_address(text: str, at: int, parts: list[tuple[int, str]]) -> bool:
    """Whether an e-mail address that holds one of the words follows within 40 characters."""
    if text.find("@", at, at + 40) < 0:
        return False
    box = _MAILBOX.search(text, at, min(len(text), at + 48))
    return box is not None and any(len(w) > 2 and w.lower() in box[0].lower() for _, w in parts)


#: Titles with the gender they tell, and given names by script and gender.
TITLES = {"mr": "m", "mister": "m", "mrs": "f", "ms": "f", "miss": "f", "dr": "", "prof": "", "herr": "m", "frau": "f", "monsieur": "m", "madame": "f", "mme": "f", "mlle": "f", "señor": "m", "señora": "f", "sr": "m", "sra": "f", "doña": "f", "господин": "m", "госпожа": "f", "κύριος": "m", "κυρία": "f"}
GIVEN = {
    ("latin", "m"): (
        "James John Robert Michael William David Richard Joseph Thomas Charles Daniel Matthew Hans Peter Klaus Jürgen Wolfgang Karl Pierre Jean Michel Philippe François Carlos José Juan Miguel Antonio Pablo "
        "Ahmed Mohammed Ali Omar Hassan Yusuf Ibrahim Raj Arjun Rahul Amit Vikram Wei Hiroshi Kenji Takashi Olumide Chinedu Kwame Lars Erik Björn Marco Giovanni Paolo Jan Piotr"
    ).split(),
    ("latin", "f"): (
        "Mary Patricia Jennifer Linda Elizabeth Barbara Susan Jessica Sarah Karen Emily Laura Anna Ursula Monika Sabine Petra Marie Sophie Camille Isabelle Nathalie María Carmen Lucía Isabel Elena Rosa "
        "Fatima Aisha Layla Zainab Noor Priya Ananya Sunita Deepa Kavita Mei Yuki Sakura Keiko Ngozi Amara Adaeze Ingrid Astrid Freya Giulia Francesca Chiara Katarzyna Agnieszka"
    ).split(),
    ("cyrillic", "m"): "Иван Сергей Алексей Дмитрий Андрей Николай Михаил Владимир Павел Олег".split(),
    ("cyrillic", "f"): "Анна Мария Елена Ольга Наталья Татьяна Ирина Светлана Екатерина Юлия".split(),
    ("greek", "m"): "Γιώργος Νίκος Δημήτρης Κώστας Γιάννης Παναγιώτης".split(),
    ("greek", "f"): "Μαρία Ελένη Κατερίνα Βασιλική Σοφία Αγγελική".split(),
}
_KNOWN = {n.lower(): k for k, names in GIVEN.items() for n in names}
_SYLLABLES = {
    "latin": "ba ber cor dal den el fer gar han hol ker lan lor mar men nor pel ras rin sel sten tar tor val ven win".split(),
    "cyrillic": "ба бер вол гор дем кар лен мар нов пет ров сав тим фед чер".split(),
    "greek": "βα γιω δη καρ λα μα νικ πα ρο σα τζι φω".split(),
}
_GIVEN_ENDS = {("latin", "m"): "o", ("latin", "f"): "a", ("cyrillic", "m"): "слав", ("cyrillic", "f"): "ина", ("greek", "m"): "ος", ("greek", "f"): "α"}


def script_of(text: str) -> str:
    return "cyrillic" if re.search("[А-яЁё]", text) else "greek" if re.search("[Α-ωά-ώ]", text) else "latin"


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c)
        total += x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x)
    return total % 10 == 0


def _mod97(iban: str) -> int:
    return int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97


def mentions(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of every entity, in order, without overlaps."""
    found: list[tuple[int, int, str]] = []
    at = text.find("@")
    while at >= 0:
        start = at
        while start and (text[start - 1].isalnum() or text[start - 1] in "._%+-"):
            start -= 1
        while start < at and text[start] in ".-%+":
            start += 1
        domain = _DOMAIN.match(text, at + 1)
        if start < at and domain:
            found.append((start, at + 1 + len(domain[0].rstrip("-.")), "email"))
        at = text.find("@", at + 1)
    for m in _DIGITS.finditer(text):
        lo, hi = max(0, m.start() - 1), min(len(text), m.end() + 1)
        for kind, pattern in (("ipv4", _IPV4), ("card", _CARD), ("ssn", _SSN), ("phone", _PHONE)):
            for x in pattern.finditer(text, lo, hi):
                if kind == "ipv4" and any(int(o) > 255 for o in x[0].split(".")):
                    continue
                if kind == "card" and not luhn("".join(filter(str.isdigit, x[0]))):
                    continue
                found.append((*x.span(), kind))
    if "=" in text or ":" in text:
        for m in _ASSIGNED.finditer(text):
            # a row of marks only stands in for a secret and isn't one
            if any(map(str.isalnum, m[1])) and _KEYWORD.search(text, max(0, m.start() - 24), m.start()):
                found.append((*m.span(1), "secret"))
        if ":" in text or "-" in text:
            found += [(*m.span(), "mac") for m in _MAC.finditer(text)]
        if ":" in text:
            found += [(*m.span(), "ipv6") for m in _IPV6.finditer(text)]
    for m in _HEX.finditer(text):
        x = m[0]
        if not x.isdigit() and not x.isalpha():
            found.append((*m.span(), "secret"))
    for mark, pattern in _MARKED:
        if mark in text:
            found += [(*m.span(), "secret") for m in pattern.finditer(text)]
    for m in _IBAN.finditer(text):
        if _mod97(m[0].replace(" ", "")) == 1:
            found.append((*m.span(), "iban"))
    for m in _CAPITALS.finditer(text):
        parts = [(p.start() + m.start(), p[0]) for p in re.finditer(r"[^ ]+", m[0])]
        head = parts[0][1].rstrip(".").lower()
        if head in TITLES:
            name = parts[1:]
        elif parts[0][1].endswith("."):
            continue
        elif head in _KNOWN:
            name = parts[:2]
        elif _CUE.search(text, max(0, m.start() - 30), m.start()):
            name = parts
        elif _own_address(text, m.end(), parts):
            name = parts
        else:
            continue
        last = name[-1][0] + len(name[-1][1].rstrip("-'’"))
        found.append((name[0][0], last, "name"))
    found.sort(key=lambda x: (x[0], -x[1]))
    out, end = [], 0
    for x in found:
        if x[0] >= end:
            out.append(x)
            end = x[1]
    return out


# ---------------------------------------------------------------------------------------------------------------------
# surrogates

#: Draws after which a surrogate leaves its format's length.
WIDEN = 8
#: Endings of family names whose feminine form is told by its ending: (masculine, feminine).
_FORMS = {"cyrillic": (("ов", "ова"), ("ев", "ева"), ("ин", "ина")), "greek": (("ίδης", "ίδου"), ("άκης", "άκη"), ("όπουλος", "οπούλου"))}


def _family(word: str) -> tuple[str, bool]:
    """The form under which a family is known, and whether the word is its feminine form."""
    for masculine, feminine in _FORMS.get(script_of(word), ()):
        if word.endswith(feminine) and len(word) > len(feminine) + 1:
            return word[: -len(feminine)] + masculine, True
    return word, False


def parts(kind: str, mention: str, before: str = "") -> list[tuple[str, str, str]]:
    """(kind, canonical form, gender) of the entities that a mention is made of. before: the text ahead, of which a title tells a name's
    gender."""
    if kind in ("card", "phone", "ssn", "iban", "mac"):
        plus = "+" if kind == "phone" and mention.startswith("+") else ""
        return [(kind, plus + "".join(c for c in mention if c.isalnum()).lower(), "")]
    if kind == "name":
        words = mention.lower().split()
        given = len(words) > 1 or words[0] in _KNOWN
        title = re.search(r"([^\W\d_]+)\.? +\Z", before)
        gender = _KNOWN[words[0]][1] if words[0] in _KNOWN else TITLES.get(title[1].lower(), "") if title else ""
        return [("given", words[0], gender)] * given + [("family", _family(w)[0], "") for w in words[given:]]
    return [(kind, mention if kind == "secret" else mention.lower(), "")]


class Stream:
    """Numbers that follow from the key, a label and how often the surrogate was drawn."""

    def __init__(self, key: bytes, label: str, attempt: int):
        self.key, self.label, self.n, self.bits, self.left = key, f"{label}\0{attempt}\0".encode("utf-8", "surrogatepass"), 0, 0, 0

    def below(self, n: int) -> int:
        if self.left < 64:
            self.bits, self.left = int.from_bytes(hmac.new(self.key, self.label + str(self.n).encode(), hashlib.sha256).digest(), "big"), 256
            self.n += 1
        self.bits, value = self.bits >> 48, self.bits & ((1 << 48) - 1)
        self.left -= 48
        return value % n


def _alike(text: str, s: Stream, hexadecimal: bool = False) -> str:
    """Each letter and digit becomes one of its class; everything else stays."""
    out = []
    for c in text:
        if "0" <= c <= "9":
            out.append(chr(48 + s.below(10)))
        elif "a" <= c <= "z":
            out.append(chr(97 + s.below(6 if hexadecimal else 26)))
        elif "A" <= c <= "Z":
            out.append(chr(65 + s.below(6 if hexadecimal else 26)))
        elif "а" <= c <= "я":
            out.append(chr(ord("а") + s.below(32)))
        elif "α" <= c <= "ω":
            out.append(chr(ord("α") + s.below(25)))
        elif c.isalpha():
            out.append(chr(97 + s.below(26)))
        else:
            out.append(c)
    return "".join(out)


def surrogate(kind: str, canon: str, attempt: int, key: bytes, gender: str = "") -> str:
    """The canonical form of the surrogate; as long as the original but for names, up to the draw at which it has to grow."""
    s = Stream(key, f"{kind}\0{canon}", attempt)
    wide = max(0, attempt - WIDEN + 1)  # letters or digits to add
    if kind == "email":
        local, _, domain = canon.rpartition("@")
        host, dot, top = domain.rpartition(".")
        return f"{_alike(local + 'a' * wide, s)}@{_alike(host, Stream(key, f'domain{chr(0)}{domain}', 0))}{dot}{top}"
    if kind == "ipv4":
        if attempt >= WIDEN:  # few addresses of this shape are left, and later few of any
            return ".".join(str(1 + s.below(254)) for _ in range(4 + max(0, wide - WIDEN)))
        spans = {1: (1, 9), 2: (10, 90), 3: (100, 155)}
        return ".".join(str((lo := spans[min(len(o), 3)])[0] + s.below(lo[1])) for o in canon.split("."))
    if kind == "card":
        body = canon[0] + _alike(canon[1:] + "0" * wide, s)
        if luhn(canon):
            body = next(body[:-1] + d for d in "0123456789" if luhn(body[:-1] + d))
        return body
    if kind == "phone":
        head = 2 if canon.startswith("+") else 1 if canon.startswith("0") else 0
        return canon[:head] + _alike(canon[head:] + "0" * wide, s)
    if kind == "iban":
        body = canon[:2].upper() + "00" + _alike(canon[4:] + "0" * wide, s).upper()
        return (body[:2] + f"{98 - _mod97(body):02d}" + body[4:]).lower()
    if kind in ("mac", "ipv6", "ssn"):
        return _alike(canon + "0" * wide, s, hexadecimal=True)
    if kind == "secret":
        if canon.startswith("-----BEGIN"):
            head, _, rest = canon.partition("KEY-----")
            body, _, tail = rest.rpartition("-----END")
            if not any(map(str.isalnum, body)):
                wide += 16  # nothing in it can change
            return f"{head}KEY-----{_alike(body + 'a' * wide, s)}-----END{tail}"
        head = re.match(r"AKIA|gh[pousr]_|sk-|xox[abprs]-|eyJ|", canon)[0]
        rest = canon[len(head) :]
        if not any(map(str.isalnum, rest)):
            wide += 16
        return head + _alike(rest + "a" * wide, s, hexadecimal=re.fullmatch("[0-9a-fA-F]+", rest) is not None)
    script = script_of(canon)
    if kind == "given":
        gender = gender or "mf"[s.below(2)]
        if attempt < WIDEN // 2:
            names = GIVEN[script, gender]
            return names[s.below(len(names))].lower()
        return "".join(_SYLLABLES[script][s.below(len(_SYLLABLES[script]))] for _ in range(1 + attempt // 4)) + _GIVEN_ENDS[script, gender]
    made = "".join(_SYLLABLES[script][s.below(len(_SYLLABLES[script]))] for _ in range(2 + s.below(2) + attempt // 4))
    return made + (_FORMS[script][0][0] if script in _FORMS else "")


def render(kind: str, mention: str, made: list[str]) -> str:
    """The surrogate in the mention's own writing: its separators, its upper case, a family name's feminine form."""
    if kind == "name":
        words, out = mention.split(), []
        for word, new in zip(words, made, strict=True):
            script = script_of(new)
            if (word is not words[0] or len(words) == 1) and script in _FORMS and _family(word.lower())[1]:
                masculine, feminine = _FORMS[script][0]
                new = new.removesuffix(masculine) + feminine
            out.append(new.upper() if mention.isupper() else new[:1].upper() + new[1:])
        return " ".join(out)
    new = made[0]
    if kind == "secret":
        return new
    if len(new) == len(mention):
        return "".join(b.upper() if a.isupper() else b for a, b in zip(mention, new, strict=True))
    if kind in ("ipv4", "ipv6", "email"):
        return new
    rest = iter(new.lstrip("+"))
    out = [next(rest, "") if a.isalnum() else a for a in mention]
    return "".join(c.upper() if a.isupper() else c for a, c in zip(mention, out, strict=True)) + "".join(rest)


def session_key(spark: SparkSession) -> bytes:
    """The key that the session's setting names, or a fresh one for this application if none is set: no key stands in the library."""
    told = spark.conf.get(KEY_SETTING, None)
    return told.encode() if told else _FRESH.setdefault(spark.sparkContext.applicationId, secrets.token_bytes(32))


_FRESH: dict[str, bytes] = {}


def entities(docs: DataFrame, text: str = "text") -> DataFrame:
    """(kind, canon, gender) of every distinct entity of the corpus. gender: of given names, by list or a title."""

    def make():
        def run(batch):
            seen = set()
            for t in batch.column(0).to_pylist():
                if t:
                    for a, b, kind in mentions(t):
                        seen.update(parts(kind, t[a:b], t[max(0, a - 24) : a]))
            cols = list(zip(*seen, strict=True)) if seen else [[]] * 3
            return pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in cols], ["kind", "canon", "gender"])

        return run

    found = arrow_map(docs.select(F.col(f"`{text}`").alias("text")), "kind string, canon string, gender string", make, 0)
    return found.groupBy("kind", "canon").agg(F.max("gender").alias("gender"))


def assign(found: DataFrame, key: bytes, rows: int | None = None) -> DataFrame:
    """(kind, canon, gender, attempt, made): a surrogate for each entity, no two alike within a kind, and none that occurs itself (but for
    given names). rows: about how many entities there are, for the number of files."""

    def make():
        def run(batch):
            kind, canon, gender, attempt = (batch.column(i).to_pylist() for i in range(4))
            made = [surrogate(k, c, n, key, g) for k, c, g, n in zip(kind, canon, gender, attempt, strict=True)]
            return pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(made, pa.string())], ["kind", "canon", "gender", "attempt", "made"])

        return run

    columns = ["kind", "canon", "gender", "attempt"]

    def draw(df: DataFrame) -> DataFrame:
        return arrow_map(df.select(*columns), "kind string, canon string, gender string, attempt int, made string", make)

    real = compact(cut(found.select("kind", "canon", "gender"), rows))
    table = compact(cut(draw(real.withColumn("attempt", F.lit(0))), rows))
    while True:
        # the entity that keeps a shared surrogate is the smallest of those drawn earliest, so that settled ones stay settled
        firsts = table.groupBy("kind", "made").agg(F.min(F.struct("attempt", "canon")).alias("first"), F.count("*").alias("n")).where("n > 1")
        shared = table.join(firsts, ["kind", "made"]).where("canon != first.canon").select("kind", "canon")
        occurs = table.where("kind != 'given'").join(real.select("kind", F.col("canon").alias("made")), ["kind", "made"], "left_semi").select("kind", "canon")
        again = compact(cut(shared.unionByName(occurs).distinct(), rows))
        if again.isEmpty():
            return table
        old = table.join(again, ["kind", "canon"], "left_semi").withColumn("attempt", F.col("attempt") + 1)
        table = compact(cut(table.join(again, ["kind", "canon"], "left_anti").select(*columns, "made").unionByName(draw(old)), rows))


def replace_text(text: str, drawn: dict[tuple[str, str], tuple[int, str]], key: bytes) -> tuple[str, list[tuple[int, int, str]]]:
    """The text with surrogates, and where they stand in it. drawn: attempt and gender of entities whose are not 0 and their own."""
    found = mentions(text)
    if not found:
        return text, []
    out, spans, at, size = [], [], 0, 0
    for a, b, kind in found:
        made = []
        for k, canon, gender in parts(kind, text[a:b], text[max(0, a - 24) : a]):
            attempt, told = drawn.get((k, canon), (0, gender))
            made.append(surrogate(k, canon, attempt, key, told))
        new = render(kind, text[a:b], made)
        out += [text[at:a], new]
        size += a - at
        spans.append((size, size + len(new), kind))
        size += len(new)
        at = b
    return "".join([*out, text[at:]]), spans


def _unused(name: str, taken: list[str]) -> str:
    while name.lower() in {x.lower() for x in taken}:
        name += "_"
    return name


def pseudonymise(docs: DataFrame, key: bytes, text: str = "text", spans: bool = True) -> DataFrame:
    """All rows with all their columns, texts with surrogates; with `spans` also n_entities and entities (start, stop, kind in the
    new text)."""
    drawn = assign(entities(docs, text), key, docs.count()).where("attempt > 0 or (kind = 'given' and gender != '')").select("kind", "canon", "attempt", "gender")
    n = drawn.count()
    column, width = docs.columns.index(text), len(docs.columns)
    at = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64()), ("kind", pa.string())]))
    fields = list(docs.schema.fields)
    if spans:
        span = T.StructType([T.StructField("start", T.LongType()), T.StructField("stop", T.LongType()), T.StructField("kind", T.StringType())])
        fields += [T.StructField(_unused("n_entities", docs.columns), T.LongType()), T.StructField(_unused("entities", docs.columns), T.ArrayType(span))]
    schema = T.StructType(fields)
    few = n <= BROADCAST_ROWS
    shared = docs.sparkSession.sparkContext.broadcast({(r[0], r[1]): (r[2], r[3]) for r in drawn.collect()} if few else {})
    source = docs
    if not few:  # each text gets the clashes among its own entities; texts are told by their digest, so ids may be null or repeat
        digest, lists = _unused("digest", docs.columns), _unused("drawn", docs.columns)

        def own():
            def run(batch):
                rows = {(d, k, c) for d, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if t for a, b, kind in mentions(t) for k, c, _ in parts(kind, t[a:b], t[max(0, a - 24) : a])}
                cols = list(zip(*rows, strict=True)) if rows else [[]] * 3
                return pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in cols], [digest, "kind", "canon"])

            return run

        of = F.sha2(F.col(f"`{text}`").cast("binary"), 256)
        pairs = arrow_map(docs.select(of.alias(digest), F.col(f"`{text}`").alias("text")), f"`{digest}` string, kind string, canon string", own)
        tables = pairs.distinct().join(drawn, ["kind", "canon"]).groupBy(digest).agg(F.collect_list(F.struct("kind", "canon", "attempt", "gender")).alias(lists))
        source = docs.withColumn(digest, of).join(tables, digest, "left")  # the digest, the rows' columns, the lists
    shift = 0 if few else 1

    def make():
        def run(batch):
            texts = batch.column(column + shift).to_pylist()
            own = [None] * len(texts) if few else batch.column(batch.num_columns - 1).to_pylist()
            made = [(t, []) if not t else replace_text(t, shared.value if few else {(x["kind"], x["canon"]): (x["attempt"], x["gender"]) for x in table or ()}, key) for t, table in zip(texts, own, strict=True)]
            cols = [batch.column(i + shift) for i in range(width)]
            cols[column] = pa.array([m[0] for m in made], cols[column].type)
            if spans:
                cols += [pa.array([len(m[1]) for m in made], pa.int64()), pa.array([[{"start": a, "stop": b, "kind": k} for a, b, k in m[1]] for m in made], at)]
            return pa.RecordBatch.from_arrays(cols, schema.names)

        return run

    return arrow_map(source, schema, make, column + shift)
