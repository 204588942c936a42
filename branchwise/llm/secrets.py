"""Secret scans: keyword automaton, anchored expressions near hits, checksum validation.

An Aho-Corasick automaton walks each whole text once (lower-cased bytes) and finds keywords.
Only where a keyword hits is the expression of its kind tried, anchored at that place. Kinds
with an embedded checksum or structure are kept only if it holds. Runs of hexadecimal digits
have no keyword and are found by one linear expression.

Base kinds: assign (keyword, sign, value), access (AKIA and capitals), hex. Added kinds:
 checked_token  prefix (ghp_, gho_, ghu_, ghs_, ghr_, npm_), 30 letters or digits, and 6
                base-62 digits that are the CRC-32 of those 30
 signed_token   three base64url parts, the first a JSON object with "alg"
 private_key    a PEM private key block up to its END line, or the BEGIN line alone

Defined cases: null or empty text has no spans; repeated rows each get their result; an empty
table gives no row; further columns are ignored. Offsets are code points, ends exclusive.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import documents, id_text, text_rows

BASE = ("assign", "access", "hex")
KINDS = (*BASE, "checked_token", "signed_token", "private_key")
# Keywords that open a secret, and the alphabet of base-62 checksums.
ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
CHECKED_PREFIXES = ("ghp_", "gho_", "ghu_", "ghs_", "ghr_", "npm_")
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"

ASSIGN = re.compile(rb"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
HEX = re.compile(rb"[0-9a-f]{24,}")
CHECKED = re.compile(rb"(?:gh[pousr]|npm)_([A-Za-z0-9]{30})([A-Za-z0-9]{6})(?![A-Za-z0-9])")
SIGNED = re.compile(rb"(eyJ[A-Za-z0-9_-]+)\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+")
KEY = re.compile(rb"-----BEGIN ([A-Z0-9 ]{0,40})PRIVATE KEY-----")


def crc62(body: bytes) -> str:
    n, out = zlib.crc32(body), ""
    while n:
        n, r = divmod(n, 62)
        out = BASE62[r] + out
    return out.rjust(6, "0")


def has_header(part: bytes) -> bool:
    try:
        head = json.loads(base64.urlsafe_b64decode(part + b"=" * (-len(part) % 4)))
    except (binascii.Error, ValueError, RecursionError):
        return False
    return isinstance(head, dict) and "alg" in head


def automaton():
    import ahocorasick

    found = ahocorasick.Automaton()
    for word in (*ASSIGN_WORDS, "akia", *CHECKED_PREFIXES, "eyj", "-----begin "):
        found.add_word(word, word)
    found.make_automaton()
    return found


def _at(kind: str, raw: bytes, start: int) -> tuple[int, bool]:
    """(end of the match at start or 0, whether it is a secret of the kind)."""
    if kind == "assign":
        m = ASSIGN.match(raw, start)
        return (m.end(), len(m[1]) >= 6) if m else (0, False)
    if kind == "access":
        m = ACCESS.match(raw, start)
        return (m.end(), m.end() - start >= 20) if m else (0, False)
    if kind == "checked_token":
        m = CHECKED.match(raw, start)
        return (m.end(), crc62(m[1]) == m[2].decode()) if m else (0, False)
    if kind == "signed_token":
        m = SIGNED.match(raw, start)
        return (m.end(), has_header(m[1])) if m else (0, False)
    m = KEY.match(raw, start)
    if not m:
        return 0, False
    close = b"-----END " + m[1] + b"PRIVATE KEY-----"
    end = raw.find(close, m.end())
    return (end + len(close) if end >= 0 else m.end()), True


def code_points(raw: bytes, places: list[int]) -> dict[int, int]:
    """Byte places (rising, between characters) as code points, in one walk over the text."""
    out, before, n = {}, 0, 0
    for p in places:
        n += len(raw[before:p].decode("utf-8", "surrogatepass"))
        out[p], before = n, p
    return out


def scan(text: str, words) -> list[tuple[str, int, int]]:
    """All spans (kind, start, end) by start, then kind as listed."""
    raw = text.encode("utf-8", "surrogatepass")
    hits: dict[str, set[int]] = {}
    for end, word in words.iter(raw.lower().decode("latin-1")):
        kind = "assign" if word in ASSIGN_WORDS else {"akia": "access", "eyj": "signed_token", "-----begin ": "private_key"}.get(word, "checked_token")
        hits.setdefault(kind, set()).add(end - len(word) + 1)
    spans = [("hex", m.start(), m.end()) for m in HEX.finditer(raw)]
    for kind, starts in hits.items():
        done = 0
        for s in sorted(starts):
            if s >= done:
                end, good = _at(kind, raw, s)
                done = max(done, end)
                if good:
                    spans.append((kind, s, end))
    spans.sort(key=lambda x: (x[1], KINDS.index(x[0])))
    if spans and len(raw) != len(text):
        at = code_points(raw, sorted({x for _, s, e in spans for x in (s, e)}))
        spans = [(k, at[s], at[e]) for k, s, e in spans]
    return spans


def find_secrets(docs: DataFrame) -> DataFrame:
    """doc_id, spans array<struct<kind, start, end>> of each whole text."""
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

    def run(batches):
        words = automaton()
        for ids, texts in text_rows(batches):
            found = [[{"kind": k, "start": s, "end": e} for k, s, e in scan(t, words)] for t in texts]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(found, kind)], names=["doc_id", "spans"])

    return id_text(docs).mapInArrow(run, "doc_id bigint, spans array<struct<kind: string, start: bigint, end: bigint>>")


def redact(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with every span, overlapping ones merged, replaced by its kind in brackets."""
    out, done = [], 0
    for kind, s, e in spans:
        if e > done:
            out += [text[done:s], f"[{kind.upper()}]"] if s >= done else []
            done = e
    return "".join(out) + text[done:]


def op6(spark, sf_dir) -> DataFrame:
    from pyspark.sql import functions as F

    found = find_secrets(documents(spark, sf_dir))
    base = F.filter("spans", lambda x: x.kind.isin(*BASE))
    joined = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x.kind, x.start, x.end)), ",")
    counts = [F.expr(f"cast(size(filter(spans, x -> x.kind = '{k}')) as bigint)").alias(f"n_{k}") for k in BASE]
    return found.select("doc_id", *counts, F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))
