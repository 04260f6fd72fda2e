"""Secret scans with multipart credential linking.

Strong patterns (assignments, access identifiers, long hexadecimal runs) are
reported by themselves.  Weak candidates (bare 40-character keys, endpoints)
mean nothing alone; each opens an interval of ``scope`` characters and is
joined with the parts that complement it: a bare key with an access
identifier, an endpoint with both an identifier and a secret.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .frames import batches, documents_only

KINDS = ("assign", "access", "hex", "key", "endpoint")  # in the order of ties
SCOPE = 400

# fixed values: the base patterns
_ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+", re.ASCII)
_HEX = re.compile(r"[0-9a-f]+", re.ASCII)
# an equals sign before a key is an assignment, after it padding
_KEY = re.compile(r"(?<![A-Za-z0-9+/])[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/=])", re.ASCII)
_URL = re.compile(r"(?:https?|s3|s3a|wss?)://[^\s\"'<>]+", re.ASCII)
_RUN = re.compile(r"[a-z0-9.-]+", re.ASCII)
_HOSTS = (".amazonaws.com", ".cloudfront.com")
_WORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
_LEAST_ASSIGN, _LEAST_ACCESS, _LEAST_HEX = 6, 20, 24

_IS_HEX = np.zeros(256, bool)
_IS_HEX[[*range(48, 58), *range(97, 103)]] = True

Span = tuple[int, int, int]  # start, number of the kind, end


def _may_hold_hex(raw: bytes) -> bool:
    """A run of 24 holds 8 consecutive multiples of three."""
    m = _IS_HEX[np.frombuffer(raw, np.uint8)[::3]]
    for step in (1, 2, 4):
        m = m[:-step] & m[step:]
    return bool(m.any())


def base_spans(text: str, raw: bytes | None = None) -> list[Span]:
    raw = text.encode() if raw is None else raw
    out: list[Span] = []
    low = raw.lower()
    if any(w in low for w in _WORDS):
        out += [(m.start(), 0, m.end()) for m in _ASSIGN.finditer(text) if len(m[2]) >= _LEAST_ASSIGN]
    if b"AKIA" in raw:
        out += [(m.start(), 1, m.end()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= _LEAST_ACCESS]
    if _may_hold_hex(raw):
        out += [(m.start(), 2, m.end()) for m in _HEX.finditer(text) if m.end() - m.start() >= _LEAST_HEX]
    return sorted(out)


def _near(starts: np.ndarray, ends: np.ndarray, parts: list[Span], scope: int) -> np.ndarray:
    """For every interval, widened by ``scope``, whether one of the parts lies in reach: a join of sorted intervals."""
    if not parts:
        return np.zeros(len(starts), bool)
    a = np.sort(np.array([p[0] for p in parts]))
    b = np.sort(np.array([p[2] for p in parts]))
    # parts that begin before the widened end, less those that end before the widened start
    return np.searchsorted(a, ends + scope, side="right") > np.searchsorted(b, starts - scope, side="left")


def _hosts(text: str, begin: int, end: int) -> list[tuple[int, int]]:
    """Bare host names of the known services in a part of the text: of a run of host characters, from its first letter or digit to the last such ending."""
    if not any(text.find(h, begin, end) >= 0 for h in _HOSTS):
        return []
    out = []
    for m in _RUN.finditer(text, begin, end):
        last, size = max((m[0].rfind(h), len(h)) for h in _HOSTS)
        first = len(m[0]) - len(m[0].lstrip(".-"))
        if first < last:
            out.append((m.start() + first, m.start() + last + size))
    return out


def endpoints(text: str) -> list[tuple[int, int]]:
    """URLs, and bare host names between them, in time linear in the text."""
    out, at = [], 0
    for m in _URL.finditer(text):
        out += [*_hosts(text, at, m.start()), m.span()]
        at = m.end()
    return out + _hosts(text, at, len(text))


def linked_spans(text: str, base: list[Span], scope: int = SCOPE) -> list[Span]:
    """Weak candidates whose complementary parts co-occur in scope."""
    access = [s for s in base if s[1] == 1]
    if not access:
        return []
    out: list[Span] = []
    taken = [s for s in base if s[1] in (0, 1)]
    keys = [(m.start(), 3, m.end()) for m in _KEY.finditer(text) if re.search("[a-z]", m[0]) and re.search("[A-Z]", m[0]) and re.search("[0-9]", m[0])]
    if keys:
        start, end = np.array([k[0] for k in keys]), np.array([k[2] for k in keys])
        inside = _near(start + 1, end - 1, taken, 0)
        out += [k for k, ok in zip(keys, _near(start, end, access, scope) & ~inside, strict=True) if ok]
    secrets = [s for s in base if s[1] in (0, 2)] + out
    places = [(a, 4, b) for a, b in endpoints(text)] if secrets else []
    if places:
        start, end = np.array([k[0] for k in places]), np.array([k[2] for k in places])
        both = _near(start, end, access, scope) & _near(start, end, secrets, scope)
        out += [k for k, ok in zip(places, both, strict=True) if ok]
    return out


def as_text(spans: list[Span]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def scan_secrets(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, n_linked, base_sha256, spans) for every row with a doc_id.

    Offsets count code points.  A null text counts as empty: no spans and the digest of the empty string.  Repeated
    rows are scanned each for itself; extra columns play no part; long texts are scanned whole.
    """

    def run(rows):
        for batch in batches(rows, 1024):
            n, sha, spans = [[], [], [], []], [], []
            for text in batch.column(1).to_pylist():
                text = text or ""
                base = base_spans(text)
                more = linked_spans(text, base, scope)
                for k in range(3):
                    n[k].append(sum(s[1] == k for s in base))
                n[3].append(len(more))
                sha.append(hashlib.sha256(as_text(base).encode()).hexdigest())
                spans.append(as_text(base + more))
            columns = [batch.column(0), *(pa.array(x, pa.int64()) for x in n), pa.array(sha, pa.string()), pa.array(spans, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_assign", "n_access", "n_hex", "n_linked", "base_sha256", "spans"])

    return documents_only(docs).mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, n_linked long, base_sha256 string, spans string")
