"""License scans: MinHash bands over overlapping windows retrieve templates, exact shingle containment verifies them.

Texts and templates are sequences of word 5-grams (lower-cased words). A template of k grams has a window width v, a power
of two up to 8, small enough that any copy that keeps `containment` of its grams leaves a run of 2v-1 grams unbroken
(`width_for`); the template's windows begin at every gram and the documents' at every v-th, so that such a run holds a
window of the document equal to one of the template's, and equal windows meet in every band. This takes grams in order
and none repeated in the template; other copies rest on the bands' probability. `bands_for` sets the number
of bands such that windows of similarity 2/3 (that of two windows of equal size sharing 0.8 of their grams) fail to meet
with probability `miss` at most; a width of one needs one band, as single grams are equal or not.

A template that met is verified on the whole document: each region of at most 1.25 k grams that holds at least
`containment` of the template's distinct grams, compared word for word, is a match. Of overlapping matches the one with
most grams stays, then the one with the higher containment, then by name.

The index of templates travels in the closure; it holds at most `block_grams` grams at a time, and a larger catalogue is
taken in blocks, each with a pass over the documents whose finds are written in between. Nothing is shuffled. Documents go
through in steps of some ten thousand grams, of which only one text's words are held as strings.

Defined results: null, empty and texts below five words match nothing and have their row; templates below five words are
refused; repeated rows each get a row; an empty table gives an empty result; a null doc_id stays null; other columns are
ignored.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hitcodec.llm.license_texts import templates as known_templates
from hitcodec.llm.ngram_join import ADD, GRAM, M1, M2, MUL, WORDS, _WordHash
from hitcodec.session import materialise

WIDTHS = (1, 2, 4, 8)
ROWS = 2
STEP = 1 << 15


def bands_for(similarity: float = 2 / 3, rows: int = ROWS, miss: float = 1e-4) -> int:
    """The fewest bands of `rows` values in which windows of this similarity fail to meet with probability `miss` at most."""
    return math.ceil(math.log(miss) / math.log1p(-(similarity**rows)))


BANDS = bands_for()


def width_for(k: int, containment: float = 0.8) -> int:
    """The widest window that an unbroken run must hold in any copy that keeps `containment` of a template's k grams.

    An edit inside a copy costs at least GRAM - 1 grams, so the kept grams lie in at most 1 + lost // (GRAM - 1) runs.
    """
    kept = math.ceil(containment * k - 1e-9)
    run = -(-kept // (1 + (k - kept) // (GRAM - 1)))
    return max(v for v in WIDTHS if v <= max(1, (run + 1) // 2))


def ordered_grams(found: list[str], words: _WordHash) -> np.ndarray:
    """64-bit hashes of all word 5-grams, in order; none below five words."""
    n = len(found) - GRAM + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(words.__getitem__, found), np.uint64, len(found))
    h = np.zeros(n, np.uint64)
    for k in range(GRAM):
        h = (h ^ w[k : n + k]) * M1
        h ^= h >> np.uint64(29)
    h *= M2
    return h ^ (h >> np.uint64(32))


def _values(grams: np.ndarray) -> np.ndarray:
    """BANDS x ROWS hash values of each gram; the smallest in a window is its MinHash value."""
    n = BANDS * ROWS
    x = (grams >> np.uint64(7)).astype(np.uint32)[None, :] * MUL[:n, None] + ADD[:n, None]
    x ^= x >> np.uint32(15)
    return x * np.uint32(0x2C1B3C6D)


def _keys(smallest: np.ndarray, width: int) -> np.ndarray:
    """Band keys of windows, bands x windows."""
    bands = 1 if width == 1 else BANDS
    part = smallest[: bands * ROWS].reshape(bands, ROWS, -1).astype(np.uint64)
    key = (np.arange(1, bands + 1, dtype=np.uint64) * M2 + np.uint64(width))[:, None]
    for k in range(ROWS):
        key = (key ^ part[:, k]) * M1
        key ^= key >> np.uint64(31)
    return key


@dataclass
class Index:
    """Templates and the band keys of their windows."""

    names: list[str]
    grams: list[dict[int, tuple[str, ...]]]  # of each template: hash -> words
    keys: dict[int, np.ndarray]  # by width: sorted keys
    owners: dict[int, np.ndarray]  # by width: the template of each key
    maybe: dict[int, np.ndarray]  # by width: which leading 16 bits of keys occur


def build_index(templates: list[tuple[str, str]], containment: float = 0.8) -> Index:
    words, made = _WordHash(), defaultdict(list)
    names, grams = [], []
    for t, (name, text) in enumerate(templates):
        found = WORDS.findall(text.lower())
        if len(found) < GRAM:
            raise ValueError(f"template {name!r} has fewer than {GRAM} words")
        h = ordered_grams(found, words)
        names.append(name)
        grams.append({int(x): tuple(found[i : i + GRAM]) for i, x in enumerate(h)})
        v = width_for(len(h), containment)
        x = _values(h)
        windows = np.lib.stride_tricks.sliding_window_view(x, v, axis=1).min(2)
        key = np.unique(_keys(windows, v))
        made[v].append((key, np.full(len(key), t, np.int32)))
    keys, owners, maybe = {}, {}, {}
    for v, parts in made.items():
        key, owner = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
        order = np.argsort(key, kind="stable")
        keys[v], owners[v] = key[order], owner[order]
        maybe[v] = np.zeros(1 << 16, bool)
        maybe[v][(key >> np.uint64(48)).astype(np.int64)] = True
    return Index(names, grams, keys, owners, maybe)


def retrieve(grams: np.ndarray, index: Index) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First and last gram of windows that meet a template's, and that template."""
    at, last, owner = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int32)]
    for base in range(0, len(grams), STEP):
        smallest, width = _values(grams[base : base + STEP]), 1
        while True:
            if width in index.keys and smallest.shape[1]:
                key = _keys(smallest, width)
                _, window = hit = np.nonzero(index.maybe[width][(key >> np.uint64(48)).astype(np.int64)])
                key = key[hit]
                low, high = np.searchsorted(index.keys[width], key, "left"), np.searchsorted(index.keys[width], key, "right")
                n = high - low
                begin = np.repeat(window * width + base, n)
                at.append(begin)
                last.append(begin + width - 1)
                place = np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())
                owner.append(index.owners[width][place])
            if width == WIDTHS[-1]:
                break
            even = smallest.shape[1] // 2 * 2
            smallest, width = np.minimum(smallest[:, 0:even:2], smallest[:, 1:even:2]), width * 2
    return np.concatenate(at), np.concatenate(last), np.concatenate(owner)


def regions(at: list[int], which: list[int], k: int, containment: float = 0.8) -> list[tuple[int, int, int]]:
    """First gram, last gram and distinct grams of disjoint regions, leftmost first, for a template of k distinct grams.

    at are the sorted places of the template's grams in a document, which says which gram stands there. A region is closed
    by the earliest gram that completes `containment`, shrunk to where it needs to begin and then stretched to its full length.
    """
    need, span = math.ceil(containment * k - 1e-9), max(k, math.floor(1.25 * k))
    found, left, i, seen = [], 0, 0, defaultdict(int)
    while i < len(at):
        seen[which[i]] += 1
        while at[left] <= at[i] - span or seen[which[left]] > 1 and left < i:
            seen[which[left]] -= 1
            if not seen[which[left]]:
                del seen[which[left]]
            left += 1
        if len(seen) >= need:
            last, held = i, set(seen)
            for j in range(i + 1, len(at)):
                if at[j] >= at[left] + span:
                    break
                if which[j] not in held:
                    held.add(which[j])
                    last = j
            found.append((at[left], at[last], len(held)))
            seen.clear()
            i = left = last + 1
            continue
        i += 1
    return found


def matches(found: list[str], grams: np.ndarray, candidates: list[int], index: Index, containment: float = 0.8) -> list[tuple[int, int, int, int, str]]:
    """First gram, last gram, distinct grams found, distinct grams of the template, name."""
    made = []
    for t in candidates:
        table = index.grams[t]
        known = np.fromiter(table, np.uint64, len(table))
        at = [int(i) for i in np.flatnonzero(np.isin(grams, known)) if tuple(found[i : i + GRAM]) == table[int(grams[i])]]
        which = [int(grams[i]) for i in at]
        made += [(*r, len(table), index.names[t]) for r in regions(at, which, len(table), containment)]
    return made


def settle(made: list[tuple]) -> list[tuple]:
    """Of overlapping matches (first, last, found, of, name) the best, by place."""
    starts, kept = [], []  # disjoint, by place
    for m in sorted(set(made), key=lambda m: (-m[2], -m[2] / m[3], m[4], m[0])):
        i = bisect_left(starts, m[0])
        if (i == 0 or kept[i - 1][1] < m[0]) and (i == len(kept) or kept[i][0] > m[1]):
            starts.insert(i, m[0])
            kept.insert(i, m)
    return kept


FOUND = "array<struct<first:long,last:long,grams:long,of:long,name:string>>"
MATCH = "array<struct<license:string,start:long,end:long,containment:double>>"


def _scan(index: Index, containment: float):
    """Batches of (doc_id, text, found so far) with the finds of an index added."""

    def handle(texts: list[str]) -> list[list[tuple]]:
        words, parts, made = _WordHash(), [], [[] for _ in texts]

        def step(first: int) -> None:
            ends = np.cumsum([len(p) for p in parts])
            if not len(ends) or not ends[-1]:
                return
            at, last, owner = retrieve(np.concatenate(parts), index)
            doc = np.searchsorted(ends, at, "right")
            inside = doc == np.searchsorted(ends, last, "right")
            wanted = defaultdict(set)
            for d, t in zip(doc[inside].tolist(), owner[inside].tolist()):
                wanted[d].add(t)
            for d, those in wanted.items():
                made[first + d] = matches(WORDS.findall(texts[first + d].lower()), parts[d], sorted(those), index, containment)

        first = held = 0
        for i, text in enumerate(texts):
            parts.append(ordered_grams(WORDS.findall(text.lower()), words))
            held += len(parts[-1])
            if held >= STEP:
                step(first)
                parts, first, held = [], i + 1, 0
        step(first)
        return made

    def scan(batches):
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            rows = [[{"first": a, "last": b, "grams": n, "of": k, "name": s} for a, b, n, k, s in m] for m in handle(texts)]
            rows = [(old or []) + new for old, new in zip(batch.column(2).to_pylist(), rows)]
            kind = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64()), ("grams", pa.int64()), ("of", pa.int64()), ("name", pa.string())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(rows, kind)], ["doc_id", "text", "found"])

    return scan


def _placed(batches):
    """Matches that stay, in code points of the text."""
    kind = pa.list_(pa.struct([("license", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("containment", pa.float64())]))
    for batch in batches:
        rows = []
        for text, found in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
            kept = settle([tuple(m[k] for k in ("first", "last", "grams", "of", "name")) for m in found or []])
            if kept:
                wanted = {m[0] for m in kept} | {m[1] + GRAM - 1 for m in kept}
                spans = {i: w.span() for i, w in enumerate(WORDS.finditer(text)) if i in wanted}
                kept = [{"license": m[4], "start": spans[m[0]][0], "end": spans[m[1] + GRAM - 1][1], "containment": m[2] / m[3]} for m in kept]
            rows.append(kept)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, kind)], ["doc_id", "matches"])


def license_scan(docs: DataFrame, templates: list[tuple[str, str]] | None = None, containment: float = 0.8, block_grams: int = 500_000) -> DataFrame:
    """doc_id, matches (license, start, end in code points, containment), a row for each row of docs."""
    templates = known_templates() if templates is None else templates
    blocks, held = [[]], 0
    for name, text in templates:
        n = len(WORDS.findall(text.lower()))
        if blocks[-1] and held + n > block_grams:
            blocks.append([])
            held = 0
        blocks[-1].append((name, text))
        held += n
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text"), F.lit(None).cast(FOUND).alias("found"))
    for i, block in enumerate(blocks):
        if i:
            rows = materialise(rows, "license-scan")
        rows = rows.mapInArrow(_scan(build_index(block, containment), containment), f"doc_id long, text string, found {FOUND}")
    return rows.mapInArrow(_placed, f"doc_id long, matches {MATCH}")


def license_digest(found: DataFrame) -> DataFrame:
    """doc_id, n_matches, licenses (distinct names, comma-joined), spans (license:start:end, comma-joined), least containment."""
    span = F.transform("matches", lambda m: F.concat_ws(":", m["license"], m["start"], m["end"]))
    return found.select(
        "doc_id",
        F.size("matches").cast("long").alias("n_matches"),
        F.array_join(F.array_sort(F.array_distinct("matches.license")), ",").alias("licenses"),
        F.array_join(span, ",").alias("spans"),
        F.array_min("matches.containment").alias("containment"),
    )
