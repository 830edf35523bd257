"""Secret scans: fixed patterns, and sliding-window Shannon entropy of each character class over candidate strings.

Candidates are maximal runs of token characters. For every class (hex digits, base-64 letters) a window slides along a run, 20 characters
wide or as wide as a run of 16 to 19; counts are changed by the character that enters and the one that leaves, and with them the entropy.
Windows of one class over its limit that touch are one span, unless the run is on the allow-list (placeholders, alphabets, identifiers,
file paths, plain words). A placeholder word that stands by itself between separators is cut out of the run and what lies before and
after it is scanned; one within a longer word allows the whole run.

Defined cases: a null text is empty; offsets are code points; spans of one kind don't overlap; repeated rows are scanned alike;
extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import math
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, table

# Fixed patterns. Either case holds for ASCII letters only.
ASSIGN = re.compile(r"(?:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 12, 18, 16

#: Width of a window, and the shortest run that is scored, with a window of its own length.
WINDOW, LEAST = 20, 16
CANDIDATE = re.compile(rf"[A-Za-z0-9+/_=-]{{{LEAST},}}")
_HEX_PIECE = re.compile(rf"[0-9a-fA-F]{{{LEAST},}}")
#: Entropy limits in bits a character of a window of 20 (at most 4.32) for each class; narrower windows have the same share of their own most.
LIMITS = {"hex": 3.0, "base64": 3.7}
# Runs that are no secrets however they look.
_PLACEHOLDERS = "example|placeholder|changeme|dummy|sample|redacted|xxxx"
_ALONE = re.compile(rf"(?i)[+/_=-]*(?<![A-Za-z0-9])(?:{_PLACEHOLDERS})(?![A-Za-z0-9])[+/_=-]*")
ALLOW = re.compile(
    rf"(?i)(?:{_PLACEHOLDERS})"
    r"|^[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}$"
    r"|abcdefghij|0123456789|qwertyuiop"
    r"|^[a-z]+(?:[-_/][a-z]+)*$|^[A-Z]?[a-z]+(?:[-_/][A-Z]?[a-z]+)*$|^[A-Z]+(?:[-_/][A-Z]+)*$"
    r"|^[0-9]+(?:[-_/][0-9]+)*$|^[-_=+/]+$"
)
_CLOG = [0.0] + [c * math.log2(c) for c in range(1, WINDOW + 1)]
KINDS = ("assign", "access", "hex", "entropy")


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Matches of the fixed patterns, those too short dropped after matching."""
    out = [("assign", *m.span()) for m in ASSIGN.finditer(text) if m.end(1) - m.start(1) >= ASSIGN_LEAST] if ("=" in text or ":" in text) else []
    if "AKIA" in text:
        out += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LEAST]
    # only runs of 16 and more count, and runs are maximal, so the pattern may ask for the length itself
    out += [("hex", *m.span()) for m in _LONG_HEX.finditer(text)]
    return out


_LONG_HEX = re.compile(rf"[0-9a-f]{{{HEX_LEAST},}}")


def window_entropy(run: str, window: int = WINDOW):
    """(start, entropy) of every window of a run: counts change by one character in and one out."""
    counts: dict[str, int] = {}
    total = 0.0  # the sum of c * log2 c
    scale = math.log2(window)
    for i, ch in enumerate(run):
        c = counts.get(ch, 0)
        total += _CLOG[c + 1] - _CLOG[c]
        counts[ch] = c + 1
        if i >= window:
            old = run[i - window]
            c = counts[old]
            total += _CLOG[c - 1] - _CLOG[c]
            counts[old] = c - 1
        if i >= window - 1:
            yield i - window + 1, scale - total / window


def _parts(run: str):
    """(start, part) of a run between the placeholder words that stand by themselves in it."""
    at = 0
    for m in _ALONE.finditer(run):
        yield at, run[at : m.start()]
        at = m.end()
    yield at, run[at:]


def _random_looking(window: str, kind: str) -> bool:
    """Whether a window's letters fit its class: a digit in it, and letters of both cases where a base-64 run is too short for a whole window."""
    if not any(c.isdigit() for c in window):
        return False
    return kind == "hex" or len(window) == WINDOW or (any(c.isupper() for c in window) and any(c.islower() for c in window))


def entropy_spans(text: str) -> list[tuple[str, int, int]]:
    """Spans of windows over their class's limit, joined where they touch, classes together."""
    out = []
    for m in CANDIDATE.finditer(text):
        for start, part in _parts(m[0]):
            if len(part) < LEAST or ALLOW.search(part) or not (any(c.isdigit() for c in part) and any(c.isalpha() for c in part)):
                continue
            at = m.start() + start
            spans: list[tuple[int, int]] = []
            for kind, limit in LIMITS.items():
                pieces = [(p.start(), p[0]) for p in _HEX_PIECE.finditer(part)] if kind == "hex" else [(0, part)]
                for base, piece in pieces:
                    width = min(len(piece), WINDOW)
                    least = limit * math.log2(width) / math.log2(WINDOW)
                    spans += [(at + base + s, at + base + s + width) for s, h in window_entropy(piece, width) if h >= least and _random_looking(piece[s : s + width], kind)]
            for lo, hi in sorted(spans):
                if out and lo <= out[-1][2]:
                    out[-1] = ("entropy", out[-1][1], max(hi, out[-1][2]))
                else:
                    out.append(("entropy", lo, hi))
    return out


def _write(spans) -> str:
    order = {k: i for i, k in enumerate(KINDS)}
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda x: (x[1], order[x[0]], x[2])))


def _scan(batches):
    for b in batches:
        cols: list[list] = [[] for _ in range(5)]
        for text in b.column(1).to_pylist():
            base = base_spans(text or "")
            more = entropy_spans(text or "")
            for i, kind in enumerate(("assign", "access", "hex")):
                cols[i].append(sum(s[0] == kind for s in base))
            cols[3].append(hashlib.sha256(_write(base).encode()).hexdigest())
            cols[4].append(_write(base + more))
        yield pa.record_batch([b.column(0), *(pa.array(c, pa.int64()) for c in cols[:3]), *(pa.array(c, pa.string()) for c in cols[3:])], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of every row of docs (doc_id, text)."""
    bound_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_scan, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redact(docs: DataFrame, mark: str = "[secret]") -> DataFrame:
    """docs with every span replaced by a mark; overlapping spans become one."""
    bound_batches(docs.sparkSession)
    at, schema = docs.columns.index("text"), docs.schema

    def cut(text: str) -> str:
        out, end = [], 0
        for _, a, b in sorted(base_spans(text) + entropy_spans(text), key=lambda x: x[1:]):
            if a >= end:
                out += [text[end:a], mark]
            end = max(end, b)
        return "".join([*out, text[end:]])

    def run(batches):
        for b in batches:
            cols = list(b.columns)
            cols[at] = pa.array([None if t is None else cut(t) for t in cols[at].to_pylist()], pa.string())
            yield pa.record_batch(cols, schema.names)

    return docs.mapInArrow(run, schema)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
