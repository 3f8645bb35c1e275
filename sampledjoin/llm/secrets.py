"""Secret scan: an Aho-Corasick keyword automaton finds where secrets may begin, regular expressions anchored there decide, and checksums carried by a secret are verified.

Defined cases: null and empty texts have no spans; each row is scanned by itself, so repeated rows and null ids are kept;
ties at a start are ordered by kind as listed. Positions count code points, the end is exclusive.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re
import zlib

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import ship, sliced

#: The base kinds' patterns, and those of further kinds with a keyword to find them by.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
#: kind: (keywords as they stand in lower case, pattern)
FURTHER = {
    "github": (("ghp_", "gho_", "ghu_", "ghs_", "ghr_"), re.compile(r"gh[pousr]_[0-9A-Za-z]{36}(?![0-9A-Za-z])")),
    "npm": (("npm_",), re.compile(r"npm_[0-9A-Za-z]{36}(?![0-9A-Za-z])")),
    "jwt": (("eyj",), re.compile(r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{16,}")),
    "pem": (("-----begin ",), re.compile(r"-----BEGIN (?:[A-Z0-9]+ )*PRIVATE KEY-----[A-Za-z0-9+/=\s]{32,}-----END (?:[A-Z0-9]+ )*PRIVATE KEY-----")),
    "google": (("aiza",), re.compile(r"AIza[0-9A-Za-z_-]{35}(?![0-9A-Za-z_-])")),
    "slack": (("xoxb-", "xoxp-", "xoxa-", "xoxr-"), re.compile(r"xox[bpar]-[0-9A-Za-z-]{20,}")),
    "stripe": (("sk_live_", "rk_live_"), re.compile(r"[sr]k_live_[0-9A-Za-z]{24,}")),
    "wif": (("5h", "5j", "5k"), re.compile(r"(?<![1-9A-HJ-NP-Za-km-z])5[HJK][1-9A-HJ-NP-Za-km-z]{49}(?![1-9A-HJ-NP-Za-km-z])")),
}
KINDS = ("assign", "access", "hex", *FURTHER)
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
BASE58 = "123456789ABCDEFGHJKLMNPQRSTUVWXYZabcdefghijkmnopqrstuvwxyz"


def crc_suffix(body: str) -> str:
    """CRC-32 of the body as six base-62 digits, as tokens carry it at their end."""
    n, out = zlib.crc32(body.encode()), ""
    for _ in range(6):
        n, r = divmod(n, 62)
        out = BASE62[r] + out
    return out


def _jwt(s: str) -> bool:
    try:
        head = json.loads(base64.urlsafe_b64decode(s.split(".")[0] + "=="))
    except (ValueError, binascii.Error):
        return False
    return isinstance(head, dict) and "alg" in head


def _wif(s: str) -> bool:
    n = 0
    for c in s:
        n = n * 58 + BASE58.index(c)
    raw = n.to_bytes(38, "big")[-37:] if n < 1 << 296 else b""
    return len(raw) == 37 and raw[0] == 0x80 and hashlib.sha256(hashlib.sha256(raw[:-4]).digest()).digest()[:4] == raw[-4:]


#: Kinds whose text carries its own check.
CHECKS = {
    "github": lambda s: crc_suffix(s[4:-6]) == s[-6:],
    "npm": lambda s: crc_suffix(s[4:-6]) == s[-6:],
    "jwt": _jwt,
    "wif": _wif,
}
_UPPER = re.compile("[A-Z]+")


def automaton() -> ahocorasick.Automaton:
    a: dict[str, list[str]] = {w: ["assign"] for w in ASSIGN_WORDS}
    a["akia"] = ["access"]
    for kind, (words, _) in FURTHER.items():
        for w in words:
            a.setdefault(w, []).append(kind)
    out = ahocorasick.Automaton()
    for w, kinds in a.items():
        out.add_word(w, (len(w), tuple(kinds)))
    out.make_automaton()
    return out


def scan(text: str | None, keywords: ahocorasick.Automaton) -> list[tuple[int, int, str]]:
    """All spans (start, end, kind), ordered by start, then kind."""
    text = text or ""
    low = text.lower()
    if len(low) != len(text):
        low = _UPPER.sub(lambda m: m[0].lower(), text)
    hits: dict[str, list[int]] = {}
    for end, (n, kinds) in keywords.iter(low):
        for kind in kinds:
            hits.setdefault(kind, []).append(end - n + 1)
    spans = [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    for kind, starts in hits.items():
        pattern = ASSIGN if kind == "assign" else ACCESS if kind == "access" else FURTHER[kind][1]
        at = 0
        for start in sorted(set(starts)):
            if start < at or not (m := pattern.match(text, start)):
                continue
            at = m.end()
            if kind == "assign":
                good = len(m[2]) >= 6
            elif kind == "access":
                good = at - start >= 20
            else:
                good = CHECKS.get(kind, lambda _: True)(m[0])
            if good:
                spans.append((start, at, kind))
    spans.sort(key=lambda s: (s[0], KINDS.index(s[2])))
    return spans


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


SCHEMA = "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, n_further bigint, base_sha256 string, spans string"


def find_secrets(docs: DataFrame) -> DataFrame:
    """One row for each row of ``docs`` (doc_id, text): counts by base kind, the digest of the base spans, and all spans."""
    ship(docs.sparkSession)

    def found(batches):
        keywords = automaton()
        for b in sliced(batches):
            rows = []
            for t in b.column(1).to_pylist():
                spans = scan(t, keywords)
                base = [s for s in spans if s[2] in KINDS[:3]]
                n = [sum(s[2] == k for s in base) for k in KINDS[:3]]
                rows.append((*n, len(spans) - len(base), hashlib.sha256(joined(base).encode()).hexdigest(), joined(spans)))
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, pa.int64()) for c in cols[:4]), *(pa.array(c, pa.string()) for c in cols[4:])], names=[x.split()[0] for x in SCHEMA.split(", ")])

    return docs.select(docs["doc_id"].cast("bigint").alias("doc_id"), "text").mapInArrow(found, SCHEMA)


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with every found span of its text replaced by its kind in brackets; overlapping spans are replaced together under the first kind."""
    ship(docs.sparkSession)
    fields = docs.columns

    def cleaned(batches):
        keywords = automaton()
        for b in batches:
            out = []
            for t in b.column(fields.index("text")).to_pylist():
                if t is None:
                    out.append(None)
                    continue
                parts, at = [], 0
                for a, e, kind in scan(t, keywords):
                    if a >= at:
                        parts += [t[at:a], f"[{kind}]"]
                    at = max(at, e)
                out.append("".join([*parts, t[at:]]))
            cols = list(b.columns)
            cols[fields.index("text")] = pa.array(out, pa.string())
            yield pa.RecordBatch.from_arrays(cols, names=fields)

    return docs.mapInArrow(cleaned, docs.schema)


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The counts of the base kinds alone, which SQL can give too."""
    return op8(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


def _any_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: The base kinds by their definition. Letters in either case are written out, as another engine's flag folds more than these.
BASE_SQL = rf"""
SELECT doc_id,
       CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), '({"|".join(map(_any_case, ASSIGN_WORDS[:4]))}|{_any_case("api")}_?{_any_case("key")})["'']? *[:=] *["'']?([A-Za-z0-9+/_.=-]+)', 2), lambda x: length(x) >= 6)) AS BIGINT) AS n_assign,
       CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20)) AS BIGINT) AS n_access,
       CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: length(x) >= 24)) AS BIGINT) AS n_hex
FROM documents
"""
