"""Secret scan: fixed patterns plus windows of high entropy over candidate strings.

Candidates are maximal runs of token characters. A window slides over each run; the counts of its characters and
their sum of c*log2(c) are updated by one character in and one out, so each step costs the same whatever the
window's length. Every character class has its own threshold in bits. Windows over it are joined to spans; without
a digit a window needs more bits. The allow-list, place holders and spans that the fixed patterns already have suppress them.

Defined results: a null text counts as empty and has no spans; a text is scanned whole at any length; repeated rows
are scanned each; an empty table gives no rows. Offsets are code points, the end exclusive.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import only

# The base patterns and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
ASSIGN_LEAST, ACCESS_LEAST = 6, 20
KEYWORDS = ("password", "passwd", "secret", "token", "api_key", "apikey")
BASE_KINDS = ("assign", "access", "hex")
KINDS = (*BASE_KINDS, "hexentropy", "entropy", "letters")

WINDOW = 20
RUN = re.compile(r"[A-Za-z0-9+/_=-]{%d,}" % WINDOW)
HEX_RUN = re.compile(r"[0-9A-Fa-f-]+")
#: Bits a window needs, by class: hexadecimal digits, the wider token alphabet, or that alphabet without a digit.
BITS = {"hexentropy": 3.0, "entropy": 3.85, "letters": 3.95}
#: Runs that look random and are not secret: version-style ids of the UUID form, paths of words.
ALLOW = (
    r"[0-9A-Fa-f]{8}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{12}",
    r"[/_=-]*(?:(?:[A-Z]?[a-z]+|[A-Z]+)[/_=-]+)+(?:[A-Z]?[a-z]+|[A-Z]+)?",
)
#: Place holders suppress the span that holds them; as a name before ``=`` or a word of their own they are only left out.
HOLDER = re.compile(r"(?i)example|sample|placeholder|changeme|dummy")
LABEL = re.compile(r"(?i)(?<![A-Z0-9+])(?:example|sample|placeholder|changeme|dummy)(?![A-Z0-9+])")
FIELD = re.compile(r"[^=]+=*|=+")


@lru_cache(maxsize=8)
def _allowed(patterns: tuple[str, ...]) -> re.Pattern:
    return re.compile("|".join(f"(?:{p})" for p in patterns)) if patterns else re.compile(r"(?!)")


def hot_windows(run: str, bits: float, window: int = WINDOW) -> list[tuple[int, int]]:
    """Joined spans of the windows of ``run`` whose Shannon entropy is at least ``bits``."""
    counts: dict[str, int] = {}
    weight, found = 0.0, []
    limit = (math.log2(window) - bits) * window + 1e-9
    term = [0.0, *(c * math.log2(c) for c in range(1, window + 2))]
    for i, ch in enumerate(run):
        c = counts.get(ch, 0)
        counts[ch] = c + 1
        weight += term[c + 1] - term[c]
        if i >= window:
            old = run[i - window]
            c = counts[old]
            counts[old] = c - 1
            weight += term[c - 1] - term[c]
        if i >= window - 1 and weight <= limit:
            lo = i - window + 1
            if found and lo <= found[-1][1]:
                found[-1][1] = i + 1
            else:
                found.append([lo, i + 1])
    return [tuple(x) for x in found]


def mixed(piece: str) -> bool:
    """Digits beside letters: prose and plain numbers have only one of them."""
    return any(c.isdigit() for c in piece) and any(c.isalpha() for c in piece)


def stretches(run: str) -> list[tuple[int, int]]:
    """Parts of a run between names and words that mark place holders."""
    if not HOLDER.search(run):
        return [(0, len(run))]
    out, at = [], 0
    for m in FIELD.finditer(run):
        name = m[0].endswith("=") and m.end() < len(run) and HOLDER.search(m[0])
        for lo, hi in [m.span()] if name else [(m.start() + w.start(), m.start() + w.end()) for w in LABEL.finditer(m[0])]:
            out.append((at, lo))
            at = hi
    return [(lo, hi) for lo, hi in (*out, (at, len(run))) if hi - lo >= WINDOW]


def hot_spans(run: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of a run's parts of high entropy; a part without a digit must reach its own bound, one without a letter is no secret."""
    kind, out = "hexentropy" if HEX_RUN.fullmatch(run) else "entropy", []
    for start, end in stretches(run):
        for lo, hi in hot_windows(run[start:end], BITS[kind]):
            lo, hi = start + lo, start + hi
            if mixed(run[lo:hi]):
                out.append((lo, hi, kind))
            elif any(c.isalpha() for c in run[lo:hi]):
                out += [(lo + a, lo + b, "letters") for a, b in hot_windows(run[lo:hi], BITS["letters"])]
    return [(lo, hi, k) for lo, hi, k in out if not HOLDER.search(run, lo, hi)]


def base_spans(text: str) -> list[tuple[int, int, str]]:
    out = []
    low = text.lower()
    if any(k in low for k in KEYWORDS):
        out += [(*m.span(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_LEAST]
    if "AKIA" in text:
        out += [(*m.span(), "access") for m in ACCESS.finditer(text) if len(m[0]) >= ACCESS_LEAST]
    out += [(*m.span(), "hex") for m in HEX.finditer(text)]
    return out


def spans_of(text: str, allow: tuple[str, ...] = ALLOW) -> tuple[list, list]:
    """(base spans, all spans) as (start, end, kind), each ordered by start, then kind as listed."""
    key = lambda s: (s[0], KINDS.index(s[2]), s[1])
    base = sorted(base_spans(text), key=key)
    more = []
    for m in RUN.finditer(text):
        run, at = m[0], m.start()
        if _allowed(allow).fullmatch(run):
            continue
        for lo, hi, kind in hot_spans(run):
            a, b = at + lo, at + hi
            if not any(s <= a and b <= e for s, e, _ in base):
                more.append((a, b, kind))
    return base, sorted(base + more, key=key)


def as_text(spans: list) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


def redact(text: str, mark: str = "[SECRET]") -> str:
    """The text with every span replaced by the mark; overlapping spans get one mark."""
    out, at = [], 0
    merged: list[list[int]] = []
    for s, e, _ in spans_of(text)[1]:
        if merged and s <= merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], e)
        else:
            merged.append([s, e])
    for s, e in merged:
        out += [text[at:s], mark]
        at = e
    return "".join(out) + text[at:] if merged else text


FOUND = "doc_id long, n_assign long, n_access long, n_hex long, base_spans string, spans string"


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", allow: tuple[str, ...] = ALLOW) -> DataFrame:
    """One row per document with the counts of each base kind and its spans as text."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, base_out, all_out = {k: [] for k in BASE_KINDS}, [], []
            for text in batch.column(1):
                base, every = spans_of(text.as_py() or "", allow)
                for k in BASE_KINDS:
                    n[k].append(sum(s[2] == k for s in base))
                base_out.append(as_text(base))
                all_out.append(as_text(every))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), *(pa.array(n[k], pa.int64()) for k in BASE_KINDS), pa.array(base_out, pa.string()), pa.array(all_out, pa.string())],
                ["doc_id", "n_assign", "n_access", "n_hex", "base_spans", "spans"],
            )

    return only(docs, doc_id=id_col, text=text_col).mapInArrow(scan, FOUND)


def redacted(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """All rows and columns with the secrets in the text replaced; null stays null."""
    place = docs.columns.index(text_col)

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [None if t is None else redact(t) for t in batch.column(place).to_pylist()]
            yield batch.set_column(place, batch.schema.field(place), pa.array(texts, batch.schema.field(place).type))

    return docs.mapInArrow(clean, docs.schema)


def digest(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()
