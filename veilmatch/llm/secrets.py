"""Secret scans with multipart credential linking.

Strong spans stand alone: assignments (a keyword, a separator, a value), access identifiers and
long hexadecimal runs. Weak parts mean little alone: values of 32 to 64 mixed characters that may be
secret keys, identifiers of 16 to 24 upper-case characters and digits, and service endpoints.
Weak parts are reported only where complementary parts stand within one scope: a possible key
with an identifier (strong or weak) or an endpoint that carries a strong part; an endpoint or a
weak identifier with a key or a strong part. A scope is a stretch of ``scope`` code points around a part that
no blank line cuts. Parts are linked by an interval join: of each wanted kind the nearest interval that ends
before a part, and the nearest that begins behind it, are looked up in sorted places, so no part is passed over.

A document is the widest scope, so linking needs no exchange: each task reads whole texts and
emits spans. Positions are code points, ends exclusive. Defined cases: a null text is empty and
has no span; repeated rows are scanned like any others; an empty table gives no rows; other columns are
ignored (or, in ``redact``, kept).
"""

from __future__ import annotations

import bisect
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.llm.common import table, tidy

# The base patterns and their least lengths.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "key", "ident", "endpoint")

KEYWORD = re.compile(r"passw|secret|token|api_?key", re.IGNORECASE | re.ASCII)
KEY = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{32,64}={0,2}(?![A-Za-z0-9+/_=-])")
IDENT = re.compile(r"(?<![A-Za-z0-9])[A-Z0-9]{16,24}(?![A-Za-z0-9])")
ENDPOINT = re.compile(r"(?:https?|postgres(?:ql)?|mysql|mongodb|redis|amqp|s3)://[^\s\"'<>]+", re.IGNORECASE | re.ASCII)
GAP = re.compile(r"\n[ \t\r]*\n")
SCOPE = 400


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    if KEYWORD.search(text):
        found += [(*m.span(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [(*m.span(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [(*m.span(), "hex") for m in HEX.finditer(text)]
    return in_order(found)


def in_order(spans: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def is_mixed(value: str) -> bool:
    return any(c.islower() for c in value) and any(c.isupper() for c in value) and any(c.isdigit() for c in value)


def linked_spans(text: str, base: list[tuple[int, int, str]], scope: int = SCOPE) -> list[tuple[int, int, str]]:
    """Weak parts with a complement in their scope."""
    weak = []
    if "://" in text:
        weak += [(*m.span(), "endpoint") for m in ENDPOINT.finditer(text)]
    weak += [(*m.span(), "key") for m in KEY.finditer(text) if is_mixed(m[0])]
    weak += [(*m.span(), "ident") for m in IDENT.finditer(text) if any(c.isdigit() for c in m[0]) and any(c.isalpha() for c in m[0])]
    # A link has two ends: one kind of weak part alone has no complement.
    if not weak or not base and len({k for _, _, k in weak}) < 2:
        return []
    gaps = [m.start() for m in GAP.finditer(text)]
    # Each part belongs to one block between blank lines; intervals of a kind are asked by their starts and by their ends.
    starts: dict[tuple[str, int], list[int]] = {}
    ends: dict[tuple[str, int], list[int]] = {}
    for s, e, k in [*base, *weak]:
        at = (k, bisect.bisect_right(gaps, s))
        starts.setdefault(at, []).append(s)
        ends.setdefault(at, []).append(e)
    for places in (*starts.values(), *ends.values()):
        places.sort()

    def beside(s: int, e: int, at: tuple[str, int]) -> bool:
        """Whether an interval of that kind and block ends in scope before s or begins in scope behind e."""
        before, behind = ends.get(at, []), starts.get(at, [])
        i, j = bisect.bisect_right(before, s) - 1, bisect.bisect_left(behind, e)
        return i >= 0 and s - before[i] <= scope or j < len(behind) and behind[j] - e <= scope

    ident, secret, end = ("access", "ident"), ("key", "assign", "hex"), ("endpoint",)
    wants = {"key": ident + end, "ident": secret, "endpoint": (*secret, "access")}
    good = [(s, e, k) for s, e, k in weak if any(beside(s, e, (other, bisect.bisect_right(gaps, s))) for other in wants[k])]
    taken = sorted((s, e) for s, e, _ in base)
    begins = [s for s, _ in taken]
    out = []
    for s, e, k in good:
        i = bisect.bisect_right(begins, s) - 1
        inside = i >= 0 and taken[i][1] >= e
        if not inside:
            out.append((s, e, k))
    return out


def spans_of(text: str | None) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """Base spans and all spans, by start and then kind."""
    base = base_spans(text) if text else []
    more = linked_spans(text, base) if text else []
    return base, in_order(base + more) if more else base


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


def scan(docs: DataFrame, doc: str = "doc_id", text: str = "text") -> DataFrame:
    fields = "doc_id long, n_assign long, n_access long, n_hex long, n_linked long, base_sha256 string, spans string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                rows = []
                for t in part.column(1).to_pylist():
                    base, every = spans_of(t)
                    kinds = [k for _, _, k in base]
                    rows.append((kinds.count("assign"), kinds.count("access"), kinds.count("hex"), len(every) - len(base), hashlib.sha256(joined(base).encode()).hexdigest(), joined(every)))
                columns = list(zip(*rows))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), *(pa.array(c, pa.int64()) for c in columns[:4]), *(pa.array(c, pa.string()) for c in columns[4:])],
                    names=["doc_id", "n_assign", "n_access", "n_hex", "n_linked", "base_sha256", "spans"],
                )

    return docs.select(F.col(doc).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(tidy(run), fields)


def redact(docs: DataFrame, text: str = "text", length: str | None = "n_chars", mark: str = "[secret]") -> DataFrame:
    """All rows and columns, each span of ``text`` replaced by ``mark``; ``length`` follows where it is a column."""
    names = docs.columns
    at = names.index(text)
    size = names.index(length) if length in names else None

    def clean(t: str | None) -> str | None:
        if not t:
            return t
        every = spans_of(t)[1]
        if not every:
            return t
        out, end = [], 0
        for s, e, _ in every:
            if s >= end:
                out += [t[end:s], mark]
            end = max(end, e)
        return "".join([*out, t[end:]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                old = part.column(at).to_pylist()
                new = [clean(t) for t in old]
                columns = list(part.columns)
                columns[at] = pa.array(new, part.schema.field(at).type)
                if size is not None:
                    n = part.column(size).to_pylist()
                    columns[size] = pa.array([k if a is b else len(b) for k, a, b in zip(n, old, new)], part.schema.field(size).type)
                yield pa.RecordBatch.from_arrays(columns, names=part.schema.names)

    return docs.mapInArrow(tidy(run), docs.schema)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
