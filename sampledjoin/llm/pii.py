"""Surrogates for personal data: detected entities receive keyed, type-consistent replacements.

Digits and letters are replaced by a keyed permutation of all strings of the same form (a Feistel network over mixed
radices), conjugated with a shift so that nothing maps to itself. A permutation has no collisions: distinct entities of
a form stay distinct, and an entity has one surrogate in the whole corpus, whatever its case or punctuation, so that references to it
still agree. Given names map within their list of the same gender and script; a name outside the lists whose
surrogate falls on a listed name is permuted again until it does not, so that the two ways can't collide either.
A given name outside the lists takes its gender from its title: a listed name of that gender is put before its scrambled
letters, so that different names stay different; under a title of the other gender, or of none, it is another entity.
``collisions`` checks the outcome over a whole corpus; op1 has the number of them in n_collisions of each row.

Defined cases: null texts stay null with no entities, empty texts empty; each row is treated by itself, so
repeated rows and null ids are kept; of overlapping finds the first, then the longest counts.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from functools import lru_cache
from itertools import takewhile

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise, ship, sliced

KEY = b"surrogates-1"
ROUNDS = 8

#: Given names by script and gender, titles by gender, and characters that replace each other.
GIVEN = {
    ("latin", "f"): "anna maria laura julia sarah emma lena sophie claire marie camille carmen lucia elena isabel alice emily grace hannah olivia".split(),
    ("latin", "m"): "john peter paul thomas michael david daniel martin lukas felix jean pierre louis antoine carlos juan miguel pablo james william".split(),
    ("cyrillic", "f"): "анна мария елена ольга наталья татьяна ирина светлана юлия екатерина".split(),
    ("cyrillic", "m"): "иван пётр сергей алексей дмитрий николай андрей михаил владимир павел".split(),
    ("greek", "f"): "μαρία ελένη κατερίνα σοφία άννα ειρήνη βασιλική δήμητρα".split(),
    ("greek", "m"): "γιώργος δημήτρης νίκος γιάννης κώστας παναγιώτης βασίλης θανάσης".split(),
}
TITLES = {
    "f": ["Mrs", "Ms", "Miss", "Madam", "Frau", "Mme", "Mlle", "Madame", "Señora", "Sra", "Doña", "Госпожа", "Κυρία"],
    "m": ["Mr", "Sir", "Herr", "Herrn", "Monsieur", "Señor", "Sr", "Don", "Господин", "Κύριος"],
    "": ["Dr", "Prof"],
}
ALPHABETS = [
    "0123456789", "aeiou", "bcdfghjklmnpqrstvwxyz", "áéíóú", "àèìòù", "âêîôû", "äëïöü", "çñ",
    "аеиоуыэюя", "бвгджзйклмнпрстфхцчшщ", "αεηιουω", "βγδζθκλμνξπρστφχψ", "άέήίόύώ",
]


def _further() -> list[str]:
    """All other letters, by script, category and whether they have one capital; of scripts with one such letter, all together."""
    known, groups, alone = set("".join(ALPHABETS)), {}, ""
    for c in map(chr, range(0x80, 0x30000)):
        if c.isalpha() and c not in known and (c.lower() == c or len(c.lower()) > 1):
            key = unicodedata.name(c, "?").split(" ")[0], unicodedata.category(c), len(c.upper()) == 1 and c.upper().lower() == c
            groups.setdefault(key, []).append(c)
    out = []
    for cs in groups.values():
        if len(cs) > 1:
            out.append("".join(cs))
        else:
            alone += cs[0]
    return [*out, alone] if alone else out


ALPHABETS += _further()
_INDEX = {a: n for n, a in enumerate(ALPHABETS)}
_CLASS = {c: (a, i) for a in ALPHABETS for i, c in enumerate(a)}
_WHO = {n: who for who, names in GIVEN.items() for n in names}
_GENDER = {t: g for g, names in TITLES.items() for t in names}

_DIGITS = re.compile(
    r"(?<![\w.+-])(?:(?P<ip>(?:\d{1,3}\.){3}\d{1,3}(?![\w]|\.\d))"
    r"|(?P<date>(?:\d{4}[-./]\d{2}[-./]\d{2}|\d{1,2}[./-]\d{1,2}[./-](?:19|20)\d{2})(?![\w-]|[./]\d))"
    r"|(?P<ssn>\d{3}-\d{2}-\d{4}(?![\w-]))"
    r"|(?P<card>[3-6]\d{3}(?:[ -]?\d{4}){2}[ -]?\d{1,7}(?!\d))"
    r"|(?P<phone>(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?)?\d{2,4}(?:[ .-]\d{2,4}){1,4}(?![\w])|\+\d{8,15}(?!\w)))"
)
_IBAN = re.compile(r"(?<!\w)[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?!\w)")
_LOCAL, _DOMAIN = re.compile(r"[\w.%+-]"), re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,24}(?![A-Za-z0-9-])")
_LETTERS = r"(?:[^\W\d_][\u0300-\u036f]*)+"
_WORD = rf"{_LETTERS}(?:[-'’]{_LETTERS})?"


def _either(words: list[str]) -> str:
    """A pattern of the words, longest first, composed or decomposed."""
    return "|".join(re.escape(w) for w in sorted({unicodedata.normalize(form, w) for w in words for form in ("NFC", "NFD")}, key=lambda w: (-len(w), w)))


_NAME = re.compile(rf"({_either(list(_GENDER))})\.? ({_WORD}(?: {_WORD}){{0,2}})")
_FULL = re.compile(rf"((?:{_either([n.capitalize() for n in _WHO])}) {_WORD}(?: {_WORD})?)")


def luhn(digits: str) -> int:
    """The check digit that belongs to the digits before it."""
    total = sum(sum(divmod(2 * int(c), 10)) if i % 2 == 0 else int(c) for i, c in enumerate(reversed(digits)))
    return -total % 10


def mod97(iban: str) -> int:
    return int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97


class Surrogates:
    def __init__(self, key: bytes = KEY):
        self.key = hashlib.blake2b(key, digest_size=32).digest()
        self.replace = lru_cache(1 << 16)(self._replace)

    def _f(self, *parts: object) -> int:
        return int.from_bytes(hashlib.blake2b("|".join(map(str, parts)).encode(), key=self.key, digest_size=32).digest(), "big")

    def _rounds(self, x: tuple[int, int], a: int, b: int, tweak: str, inverse: bool) -> tuple[int, int]:
        left, right = x
        for r in reversed(range(ROUNDS)) if inverse else range(ROUNDS):
            sign = -1 if inverse else 1
            if r % 2:
                right = (right + sign * self._f(tweak, a, b, r, left)) % b
            else:
                left = (left + sign * self._f(tweak, a, b, r, right)) % a
        return left, right

    def permute(self, values: list[int], radices: list[int], tweak: str) -> list[int]:
        """A permutation without fixed points of all value lists under these radices (where there are at least two)."""
        half = len(radices) // 2

        def number(v, r):
            n = 0
            for x, m in zip(v, r, strict=True):
                n = n * m + x
            return n

        def product(r):
            n = 1
            for m in r:
                n *= m
            return n

        a, b = product(radices[:half]), product(radices[half:])
        left, right = self._rounds((number(values[:half], radices[:half]), number(values[half:], radices[half:])), a, b, tweak, False)
        n = (left * b + right + 1) % (a * b)
        left, right = self._rounds(divmod(n, b), a, b, tweak, True)
        out: list[int] = []
        for n, r in ((right, radices[half:]), (left, radices[:half])):
            for m in reversed(r):
                n, x = divmod(n, m)
                out.append(x)
        return out[::-1]

    def like(self, text: str, tweak: str) -> str:
        """Letters and digits replaced within their alphabets; case and all else stay."""
        low = [c.lower() if len(c.lower()) == 1 else c for c in text]
        at = [i for i, c in enumerate(low) if c in _CLASS]
        if not at:
            return text
        classes = [_CLASS[low[i]] for i in at]
        # the form: which alphabets follow each other, whatever the case and the punctuation
        form = tweak + ":" + ",".join(str(_INDEX[a]) for a, _ in classes)
        new = self.permute([k for _, k in classes], [len(a) for a, _ in classes], form)
        out = list(text)
        for i, (a, _), k in zip(at, classes, new, strict=True):
            out[i] = a[k].upper() if text[i].isupper() else a[k]
        return "".join(out)

    def _digits(self, text: str, keep: int, tweak: str) -> str:
        """All digits but the first ``keep`` replaced."""
        at = [i for i, c in enumerate(text) if c.isdecimal()]
        new = self.permute([int(text[i]) for i in at[keep:]], [10] * len(at[keep:]), f"{tweak}:{len(at)}:{''.join(text[i] for i in at[:keep])}") if len(at) > keep else []
        out = list(text)
        for i, k in zip(at[keep:], new, strict=True):
            out[i] = str(k)
        return "".join(out)

    def given(self, name: str, gender: str, tweak: str = "given") -> str:
        low = name.lower()
        if gender and low not in _WHO:
            return self._gendered(name, gender)
        if low in _WHO:
            names = GIVEN[_WHO[low]]
            (k,) = self.permute([names.index(low)], [len(names)], f"{tweak}:{_WHO[low]}")
            return names[k].capitalize() if name[0].isupper() else names[k]
        return self._surname(name)

    def _gendered(self, name: str, gender: str) -> str:
        """For a name whose gender only its title tells: a listed name of that gender, a hyphen and the scrambled name, so that different names stay different."""
        low = name.lower()
        script = next((s for s in ("cyrillic", "greek") if s.upper() in unicodedata.name(next((c for c in low if c.isalpha()), "a"), "")), "latin")
        names = GIVEN[script, gender]
        k = self._f("gendered", gender, unicodedata.normalize("NFC", low))
        first = names[k % len(names)]
        return f"{first.capitalize() if name[0].isupper() else first}-{self._surname(name)}"

    def _replace(self, kind: str, text: str) -> str:
        if kind == "email":
            local, _, domain = text.rpartition("@")
            host, _, top = domain.rpartition(".")
            return f"{self.like(local, 'local')}@{self.like(host, 'host')}.{top}"
        if kind == "ip":
            new = self.permute([int(x) for x in text.split(".")], [256] * 4, "ip")
            return ".".join(map(str, new))
        if kind == "card":
            digits = [c for c in text if c.isdecimal()]
            off = (int(digits[-1]) - luhn("".join(digits[:-1]))) % 10
            body = self._digits("".join(digits[:-1]), 1, "card")
            new = iter(body + str((luhn(body) + off) % 10))
            return "".join(next(new) if c.isdecimal() else c for c in text)
        if kind == "phone":
            plain = re.sub(r"\D", "", text)
            return self._digits(text, (1 if plain[0] in "17" else 2) if text[0] == "+" else 0, "phone")
        if kind == "ssn":
            return self._digits(text, 0, "ssn")
        if kind == "iban":
            plain = text.replace(" ", "")
            body = self.like(plain[4:], f"iban:{plain[:2]}")
            check = 98 - mod97(f"{plain[:2]}00{body}")
            new = iter(f"{plain[:2]}{check:02d}{body}")
            return "".join(c if c == " " else next(new) for c in text)
        gender, _, name = unicodedata.normalize("NFC", text).partition("/")
        first, gap, rest = name.partition(" ")
        if not gap:
            return self.given(first, gender) if first.lower() in _WHO else self._surname(first)
        return " ".join([self.given(first, gender), *(self._surname(x) for x in rest.split(" "))])

    def _surname(self, name: str) -> str:
        name = unicodedata.normalize("NFC", name)
        out = self.like(name, "name")
        while out.lower() in _WHO:
            out = self.like(out, "name")
        return out


def detect(text: str | None) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, entity), without overlaps. A name's entity is its title's gender, a stroke and the name."""
    text = text or ""
    found: list[tuple[int, int, str, str]] = []
    at = text.find("@")
    while at >= 0:
        start = at
        while start and _LOCAL.match(text[start - 1]):
            start -= 1
        while start < at and text[start] in ".%+-":
            start += 1
        m = _DOMAIN.match(text, at + 1)
        if m and start < at:
            found.append((start, m.end(), "email", text[start : m.end()]))
        at = text.find("@", at + 1)
    for m in _DIGITS.finditer(text):
        kind, s = m.lastgroup, m[0]
        n = sum(c.isdecimal() for c in s)
        if kind == "date" or not s.isascii() or kind == "ip" and any(int(x) > 255 for x in s.split(".")):
            continue
        if kind == "phone" and not 7 <= n <= 15 or kind == "card" and not 13 <= n <= 19:
            continue
        found.append((m.start(), m.end(), kind, s))
    for m in _IBAN.finditer(text):
        if 15 <= len(m[0].replace(" ", "")) <= 34 and mod97(m[0].replace(" ", "")) == 1:
            found.append((m.start(), m.end(), "iban", m[0]))
    for pattern in (_NAME, _FULL):
        for m in pattern.finditer(text):
            if m.start() and (text[m.start() - 1].isalnum() or text[m.start() - 1] == "_"):
                continue
            last = m.lastindex
            words = list(takewhile(lambda w: w[0].isupper(), m[last].split(" ")))
            if len(words) >= 3 - last:  # a title needs a name after it, a given name a surname
                name = " ".join(words)
                found.append((m.start(last), m.start(last) + len(name), "name", f"{_GENDER[unicodedata.normalize('NFC', m[1])] if last == 2 else ''}/{name}"))
    found.sort(key=lambda x: (x[0], -x[1]))
    out: list[tuple[int, int, str, str]] = []
    for x in found:
        if not out or x[0] >= out[-1][1]:
            out.append(x)
    return out


def canonical(kind: str, entity: str) -> str:
    """What makes two finds the same entity."""
    if kind in ("card", "phone", "ssn"):
        return ("+" if entity[0] == "+" else "") + re.sub(r"\D", "", entity)
    if kind == "iban":
        return entity.replace(" ", "")
    if kind == "ip":
        return ".".join(str(int(x)) for x in entity.split("."))
    if kind == "name":
        gender, _, entity = unicodedata.normalize("NFC", entity).lower().partition("/")
        first, gap, _ = entity.partition(" ")
        return f"{gender}/{entity}" if gender and gap and first not in _WHO else entity
    return unicodedata.normalize("NFC", entity).lower()


_ENTITY = T.StructType([T.StructField(n, t) for n, t in (("kind", T.StringType()), ("start", T.LongType()), ("end", T.LongType()), ("surrogate", T.StringType()), ("entity_hash", T.StringType()), ("surrogate_hash", T.StringType()))])


def replace_entities(docs: DataFrame, key: bytes = KEY) -> DataFrame:
    """``docs`` with its text's entities replaced, and pii_entities: what was found where (positions of the original, in code points), its surrogate, and keyed hashes of both canonical forms."""
    ship(docs.sparkSession)
    docs = docs.drop("pii_entities")
    fields = docs.columns
    at = fields.index("text")

    def made(batches):
        who = Surrogates(key)
        tag = lambda s: hashlib.blake2b(s.encode(), key=who.key, digest_size=12).hexdigest()
        for b in sliced(batches):
            texts, entities = [], []
            for t in b.column(at).to_pylist():
                parts, last, own = [], 0, []
                for start, end, kind, entity in detect(t):
                    new = who.replace(kind, entity)
                    parts += [t[last:start], new]
                    last = end
                    own.append({"kind": kind, "start": start, "end": end, "surrogate": new, "entity_hash": tag(kind + canonical(kind, entity)), "surrogate_hash": tag(kind + canonical(kind, "/" + new if kind == "name" else new))})
                texts.append(t if t is None else "".join([*parts, t[last:]]))
                entities.append(own)
            cols = list(b.columns)
            cols[at] = pa.array(texts, pa.string())
            kind = pa.struct([(f.name, pa.int64() if f.dataType == T.LongType() else pa.string()) for f in _ENTITY.fields])
            yield pa.RecordBatch.from_arrays([*cols, pa.array(entities, pa.list_(kind))], names=[*fields, "pii_entities"])

    return docs.mapInArrow(made, T.StructType([*docs.schema.fields, T.StructField("pii_entities", T.ArrayType(_ENTITY))]))


def collisions(replaced: DataFrame) -> DataFrame:
    """Rows only where distinct entities share a surrogate, or an entity has several: (kind, hash, side, n). Counts are summed before the shuffle, so that frequent entities don't meet in a task."""
    e = replaced.select(F.explode("pii_entities").alias("e")).select("e.kind", "e.entity_hash", "e.surrogate_hash").distinct()
    one = lambda of, n: e.groupBy("kind", F.col(of).alias("hash")).agg(F.count("*").alias("n")).where("n > 1").select("kind", "hash", F.lit(n).alias("side"), "n")
    return one("surrogate_hash", "surrogate").union(one("entity_hash", "entity"))


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id"), "text")
    out = materialise(replace_entities(docs), "surrogates")
    clashes = collisions(out).count()
    count = lambda k: F.size(F.filter("pii_entities", lambda e: e["kind"] == k)).cast("bigint")
    return out.select("doc_id", F.size("pii_entities").cast("bigint").alias("n_entities"), *(count(k).alias(f"n_{k}") for k in ("email", "phone", "card", "ip", "ssn", "iban", "name")), F.col("pii_entities").alias("entities"), "text", F.lit(clashes).cast("bigint").alias("n_collisions"))
