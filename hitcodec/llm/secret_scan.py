"""Secret scans with multipart credential linking.

Base finds (assignments, access identifiers, long hexadecimal runs) are always reported. On top of them, weak parts that
alone prove nothing (free-standing secrets of 32 to 64 mixed characters, endpoints) are reported only where
complementary parts co-occur: an interval join links each access identifier to secrets and endpoints whose spans begin
within `reach` code points of it inside the same scope (a paragraph: text between blank lines). The join bisects the
interval of each access identifier in the sorted starts and goes on where the last interval ended, so that every part in
reach is linked, each is visited once, and no pairs are made.

Defined results: null text is empty; spans count code points, end exclusive; parts that overlap a base find are that
find; a null doc_id is kept as it is; repeated rows each get a row; an empty table gives an empty result; other columns
are ignored. The whole text of a document, however long, is one string in one task.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left, bisect_right

import pyarrow as pa
from pyspark.sql import DataFrame

# The base patterns.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex")
LEAST_VALUE = 6

# Weak parts of the linking.
FREE = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{32,64}={0,2}(?![A-Za-z0-9+/_=-])")
ENDPOINT = re.compile(r"(?:https?|s3|jdbc:\w+|postgres|mysql|redis|amqp|ftp)://[^\s\"'<>]{4,}|\b(?:host|endpoint|region|server)\x20*[:=]\x20*[\"']?[A-Za-z0-9.:_-]{4,}", re.A)
BLANK = re.compile(r"\n[\x20\t\r]*\n")


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the base finds, by start, then kind as listed."""
    found = []
    if ":" in text or "=" in text:
        found += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_VALUE]
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text)]
    found += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


def _mixed(value: str) -> bool:
    return any(c.isdigit() for c in value) and any(c.isupper() for c in value) and any(c.islower() for c in value)


def linked_spans(text: str, base: list[tuple[int, int, str]], reach: int = 400) -> list[tuple[int, int, str]]:
    """Weak parts that complete a credential: free secrets and endpoints near an access identifier of their scope."""
    anchors = [s for s in base if s[2] == "access"]
    if not anchors:
        return []
    taken = sorted(base)
    ends = [m.end() for m in BLANK.finditer(text)]
    scope = lambda at: bisect_left(ends, at + 1)

    def free_of_base(s: tuple[int, int]) -> bool:
        i = bisect_left(taken, (s[1],))
        return all(t[1] <= s[0] for t in taken[max(0, i - 4) : i])

    parts = {
        "secret": [m.span() for m in FREE.finditer(text) if _mixed(m[0]) and free_of_base(m.span())],
        "endpoint": [m.span() for m in ENDPOINT.finditer(text) if free_of_base(m.span())],
    }
    found = set()
    for kind, spans in parts.items():
        starts = [s[0] for s in spans]
        done = 0  # anchors come by start, so that both ends of their intervals only rise: spans before `done` were visited
        for a in anchors:
            k = scope(a[0])
            first = max(a[0] - reach, ends[k - 1] if k else 0)
            last = min(a[0] + reach, ends[k] - 1 if k < len(ends) else len(text))
            i, j = max(done, bisect_left(starts, first)), bisect_right(starts, last)
            found.update((*s, kind) for s in spans[i:j])
            done = max(done, j)
    # an endpoint alone completes nothing: it needs a secret (weak or assigned) in the same scope
    secret_scopes = {scope(s[0]) for s in found if s[2] == "secret"} | {scope(s[0]) for s in base if s[2] in ("assign", "hex")}
    return sorted(s for s in found if s[2] == "secret" or scope(s[0]) in secret_scopes)


def _written(spans) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in spans)


ORDER = {k: i for i, k in enumerate((*KINDS, "secret", "endpoint"))}


def scan_text(text: str | None, reach: int = 400) -> tuple[int, int, int, str, str]:
    """n_assign, n_access, n_hex, base spans and all spans as written."""
    text = text or ""
    base = base_spans(text)
    every = sorted([*base, *linked_spans(text, base, reach)], key=lambda s: (s[0], ORDER[s[2]])) if base else base
    return (*(sum(s[2] == k for s in base) for k in KINDS), _written(base), _written(every))


def secret_scan(docs: DataFrame, reach: int = 400) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base (spans as written), base_sha256, spans."""
    names = ["doc_id", "n_assign", "n_access", "n_hex", "base", "base_sha256", "spans"]

    def scan(batches):
        for batch in batches:
            made = [scan_text(t, reach) for t in batch.column(1).to_pylist()]
            columns = [pa.array([m[i] for m in made], pa.int64()) for i in range(3)]
            written = [pa.array([m[3] for m in made], pa.string()), pa.array([hashlib.sha256(m[3].encode()).hexdigest() for m in made], pa.string()), pa.array([m[4] for m in made], pa.string())]
            yield pa.RecordBatch.from_arrays([batch.column(0), *columns, *written], names)

    rows = docs.selectExpr("cast(doc_id as long) as doc_id", "text")
    return rows.mapInArrow(scan, "doc_id long, n_assign long, n_access long, n_hex long, base string, base_sha256 string, spans string")
