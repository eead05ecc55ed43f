"""Secret scanning: fixed patterns, and entropy of sliding windows.

Three base kinds are plain patterns. The method adds `entropy` spans: in each
candidate string (an unbroken run of token characters) a window slides and
its Shannon entropy is kept up to date from the counts of the character that
enters and the one that leaves. Hexadecimal and base64-like candidates have
their own window and threshold. Windows at or over it are merged to a span.
An allow-list suppresses what is known to be harmless.

Edge cases: null text counts as empty; offsets are code points, ends
exclusive; repeated rows give repeated rows; only the named columns are read,
or for redact() passed through.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from .memory import tidy

# Fixed values of the contract: the three patterns and least lengths.
_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")  # a maximal run of 24 or more
LEAST = {"assign": 6, "access": 20, "hex": 24}

KINDS = ("assign", "access", "hex", "entropy")
_CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
_HEX_ONLY = re.compile(r"[0-9a-fA-F]+")
#: (window, bits): a window of random characters of the class lies above, words and counters below; a shorter string is one window, its bits in proportion to the logarithm of its length.
THRESHOLDS = {"hex": (20, 2.9), "base64": (24, 3.8)}
#: Harmless shapes: UUIDs, dates and versions, runs of one separator, data-free placeholders.
ALLOWED = (
    re.compile(r"[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}"),
    re.compile(r"[0-9_./=+-]+"),
    re.compile(r"(?i).*(example|placeholder|changeme|dummy|lorem|xxxx).*"),
    re.compile(r"(?i)(https?|ftp)[:/].*"),
)
_CLOG = [0.0] + [c * math.log2(c) for c in range(1, 129)]


def windows_over(s: str, width: int, bits: float) -> list[tuple[int, int]]:
    """Merged ranges of s that are covered by windows of `width` with entropy of at least `bits`."""
    if len(s) < width:
        return []
    counts: dict[str, int] = {}
    total = 0.0
    out: list[tuple[int, int]] = []
    for i, c in enumerate(s):
        k = counts.get(c, 0)
        total += _CLOG[k + 1] - _CLOG[k]
        counts[c] = k + 1
        if i >= width:
            gone = s[i - width]
            k = counts[gone]
            total += _CLOG[k - 1] - _CLOG[k]
            counts[gone] = k - 1
        if i >= width - 1 and math.log2(width) - total / width >= bits:
            start, end = i - width + 1, i + 1
            if out and start <= out[-1][1]:
                out[-1] = (out[-1][0], end)
            else:
                out.append((start, end))
    return out


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Disjoint ranges, in order, that cover the same places."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = out[-1][0], max(out[-1][1], b)
        else:
            out.append((a, b))
    return out


def outside(start: int, end: int, base: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The parts of a range that no span of base (disjoint, in order) has told already."""
    out = []
    for a, b in _from(base, start):
        if a >= end:
            break
        if a > start:
            out.append((start, a))
        start = max(start, b)
    return [*out, (start, end)] if start < end else out


def _from(base: list[tuple[int, int]], start: int) -> Iterator[tuple[int, int]]:
    for i in range(max(0, bisect_right(base, (start, start)) - 1), len(base)):
        yield base[i]


def find(text: str | None) -> list[tuple[str, int, int]]:
    """All spans (kind, start, end) of one text, by start, then kind as listed."""
    t = text or ""
    spans: list[tuple[str, int, int]] = []
    low = t.lower()
    if "pass" in low or "secret" in low or "token" in low or "api" in low:
        spans += [("assign", m.start(), m.end()) for m in _ASSIGN.finditer(t) if len(m[2]) >= LEAST["assign"]]
    if "AKIA" in t:
        spans += [("access", m.start(), m.end()) for m in _ACCESS.finditer(t) if m.end() - m.start() >= LEAST["access"]]
    spans += [("hex", m.start(), m.end()) for m in _HEX.finditer(t)]
    base = merged([(s, e) for _, s, e in spans])
    for m in _CANDIDATE.finditer(t):
        word = m[0]
        if any(a.fullmatch(word) for a in ALLOWED):
            continue
        width, bits = THRESHOLDS["hex" if _HEX_ONLY.fullmatch(word) else "base64"]
        if len(word) < width:
            width, bits = len(word), bits * math.log2(len(word)) / math.log2(width)
        for s, e in windows_over(word, width, bits):
            spans += [("entropy", a, b) for a, b in outside(s + m.start(), e + m.start(), base)]
    return sorted(spans, key=lambda x: (x[1], KINDS.index(x[0]), x[2]))


_SPAN = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())])


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans): every span of every whole text."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [[{"kind": k, "start": s, "end": e} for k, s, e in find(t.as_py())] for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.list_(_SPAN))], names=["doc_id", "spans"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, spans array<struct<kind:string,start:int,end:int>>")


def masked(text: str, spans: list[tuple[str, int, int]]) -> str:
    """text with each merged range of spans replaced by a mark that names the first kind."""
    out, at = [], 0
    for kind, s, e in spans:
        if e <= at:
            continue
        if s >= at:
            out += [text[at:s], f"<{kind}>"]
        at = max(at, e)
    return "".join([*out, text[at:]])


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the secrets in text_col masked; all rows and columns stay, null text stays null."""
    at = docs.columns.index(text_col)

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            clean = []
            for v in b.column(at):
                t = v.as_py()
                spans = find(t)
                clean.append(masked(t, spans) if spans else t)
            cols = list(b.columns)
            cols[at] = pa.array(clean, pa.string())
            yield pa.RecordBatch.from_arrays(cols, schema=b.schema)

    return docs.mapInArrow(run, docs.schema)
