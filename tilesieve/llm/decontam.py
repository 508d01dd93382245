"""Benchmark decontamination by q-gram lemma filtering.

A window of a benchmark item and a region of a document that differ by at most k edits share at least
``w + 1 - q - k q`` q-grams, all within k diagonals of one another. So the q-grams that a document
shares with the windows are counted in overlapping bands of diagonals; only bands that meet the bound
are verified, by alignment inside the band. Bands of one window that touch are verified once, together.

Where text and window are both repetitive, their shared q-grams are more than the text is long. There the
count costs more than it saves, and the whole segment is aligned: the same answer, in time that grows with
the text alone.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilesieve.llm.bytewords import mix
from tilesieve.llm.common import frugal, ship, text_slices

ship(__name__)

Q = 12
#: Characters of an item that one window covers, and how far windows lie apart.
WINDOW, STRIDE = 96, 48
#: Edits allowed, as a share of a window.
EDITS = 0.05
#: Most characters of benchmark text in one pass over the documents; more items take more passes. An index
#: takes some 45 bytes a character in each worker.
PASS_CHARS = 2_000_000
#: Texts are searched in segments of so many characters, which overlap by more than a match is long.
SEGMENT = 1 << 18
#: Shared q-grams of one window, as a multiple of the segment, beyond which aligning is cheaper than counting.
DENSE = 2
#: Most shared q-grams that are counted at once.
HITS = 2_000_000

_FOLD = np.arange(0x250, dtype=np.uint32)
_FOLD[65:91] += 32
for _c in range(0xC0, 0x250):
    if len(chr(_c).lower()) == 1:
        _FOLD[_c] = ord(chr(_c).lower())
_FOLD[[9, 10, 11, 12, 13, 0xA0]] = 32


def normal(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Code points in lower case with each run of white space as one blank, and where each stood."""
    chars = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    chars = np.where(chars < len(_FOLD), _FOLD[np.minimum(chars, len(_FOLD) - 1)], chars)
    keep = np.ones(len(chars), bool)
    keep[1:] = (chars[1:] != 32) | (chars[:-1] != 32)
    at = np.flatnonzero(keep)
    return chars[at], at


def gram_hashes(chars: np.ndarray, q: int) -> np.ndarray:
    """A 64-bit hash of each run of q characters."""
    n = len(chars) - q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h, c = np.zeros(n, np.uint64), chars.astype(np.uint64)
    for i in range(q):
        h *= np.uint64(0x100000001B3)
        h += c[i : i + n]
    return mix(h)


def end_edits(window: np.ndarray, region: np.ndarray, k: int) -> np.ndarray | None:
    """Fewest edits from ``window`` to any stretch that ends at each place of ``region``; None if more than k at all."""
    n = len(region)
    step = np.arange(n + 1, dtype=np.int32)
    row, nxt = np.zeros(n + 1, np.int32), np.empty(n + 1, np.int32)
    for i, c in enumerate(window, 1):
        nxt[0] = i
        np.minimum(row[:-1] + (region != c), row[1:] + 1, out=nxt[1:])
        nxt -= step
        np.minimum.accumulate(nxt, out=nxt)
        nxt += step
        if nxt.min() > k:
            return None
        row, nxt = nxt, row
    return row


def banded_edits(window: np.ndarray, region: np.ndarray, k: int) -> int:
    """Fewest edits from ``window`` to any stretch of ``region``; k + 1 if more than k."""
    row = end_edits(window, region, k)
    return k + 1 if row is None else int(row.min())


@dataclass
class Index:
    """Distinct windows of a pass's items, and the sorted q-grams of all windows with where each occurs."""

    items: list[list[int]]
    texts: list[np.ndarray]
    edits: np.ndarray
    bound: np.ndarray
    grams: np.ndarray
    first: np.ndarray
    window: np.ndarray
    offset: np.ndarray
    filter: np.ndarray
    q: int
    longest: int


def build_index(rows: list[tuple[int, str]], *, q: int = Q, window: int = WINDOW, stride: int = STRIDE, share: float = EDITS) -> Index:
    """Windows of at most ``window`` characters; an item's last one ends with it.

    A window may differ by ``share`` of its characters, rounded down; one shorter than 2q must occur as it
    is. Items shorter than q have no q-gram and are in no window.
    """
    known: dict[bytes, int] = {}
    items, texts, edits = [], [], []
    for item, text in rows:
        chars = normal(text or "")[0]
        if len(chars) and chars[0] == 32:
            chars = chars[1:]
        if len(chars) and chars[-1] == 32:
            chars = chars[:-1]
        if len(chars) < q:
            continue
        size = min(window, len(chars))
        for s in sorted({*range(0, len(chars) - size + 1, stride), len(chars) - size}):
            part = chars[s : s + size]
            place = known.setdefault(part.tobytes(), len(texts))
            if place == len(texts):
                # a window of 2q characters or more has a q-gram left after all its edits, so the lemma holds
                items.append([]), texts.append(part.copy()), edits.append(int(share * size) if size >= 2 * q else 0)
            if not items[place] or items[place][-1] != item:
                items[place].append(item)
    hashes = [gram_hashes(t, q) for t in texts]
    sizes = np.array([len(h) for h in hashes], np.int64)
    every = np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)
    which = np.repeat(np.arange(len(texts), dtype=np.int32), sizes)
    offset = (np.arange(len(every)) - np.repeat(np.cumsum(sizes) - sizes, sizes)).astype(np.int16)
    order = np.argsort(every, kind="stable")
    grams, first = np.unique(every[order], return_index=True)
    member = np.zeros(1 << 22, bool)
    member[(grams >> np.uint64(42)).astype(np.int64)] = True
    edits = np.array(edits, np.int64)
    return Index(items, texts, edits, sizes - edits * q, grams, np.append(first, len(every)), which[order], offset[order], member, q, max(map(len, texts), default=0))


def _spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The numbers from each ``first`` on, ``count`` of them, one run after another."""
    return np.repeat(first - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))


def _joined(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Sorted spans, those that meet as one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = out[-1][0], max(b, out[-1][1])
        else:
            out.append((a, b))
    return out


def _bands(index: Index, windows: np.ndarray, at: np.ndarray, place: np.ndarray, length: int) -> dict[int, list[tuple[int, int]]]:
    """For each of ``windows``, the regions that a band of diagonals with enough shared q-grams covers."""
    wanted = np.zeros(len(index.texts), bool)
    wanted[windows] = True
    hit = _spread(index.first[place], index.first[place + 1] - index.first[place])
    pos = np.repeat(at, index.first[place + 1] - index.first[place])
    mine = wanted[index.window[hit]]
    hit, pos = hit[mine], pos[mine]
    window = index.window[hit].astype(np.int64)
    diagonal = pos - index.offset[hit] + SEGMENT  # never negative
    k, width = index.edits[window], 2 * index.edits[window] + 1
    out: dict[int, list[tuple[int, int]]] = {}
    for shift in (0, 1):  # bands overlap by half, so k diagonals either side of any lie in one band
        band = (diagonal + shift * k) // width
        order = np.lexsort((pos, band, window))
        w, b, p = window[order], band[order], pos[order]
        new = np.concatenate([[True], (w[1:] != w[:-1]) | (b[1:] != b[:-1])])
        fresh = new | np.concatenate([[True], p[1:] != p[:-1]])
        heads = np.flatnonzero(new)
        passed = heads[np.add.reduceat(fresh.astype(np.int64), heads) >= index.bound[w[heads]]] if len(heads) else heads
        w = w[passed]
        low = b[passed] * (2 * index.edits[w] + 1) - shift * index.edits[w] - SEGMENT
        for j, a in zip(w.tolist(), low.tolist(), strict=True):
            e = int(index.edits[j])
            out.setdefault(j, []).append((max(0, a - e), min(length, a + 2 * e + 1 + len(index.texts[j]) + e)))
    return out


def regions(index: Index, chars: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(window, from, to) of the regions of a segment that may hold a window: all that do lie in one."""
    h = gram_hashes(chars, index.q)
    at = np.flatnonzero(index.filter[(h >> np.uint64(42)).astype(np.int64)]) if len(h) else np.zeros(0, np.int64)
    if not len(at) or not len(index.grams):
        return
    place = np.minimum(np.searchsorted(index.grams, h[at]), len(index.grams) - 1)
    same = index.grams[place] == h[at]
    at, place = at[same], place[same]
    if not len(at):
        return
    # a window of which too few q-grams occur in the segment at all is out; the others' shared ones are counted
    grams, often = np.unique(place, return_counts=True)
    count = index.first[grams + 1] - index.first[grams]
    held = index.window[_spread(index.first[grams], count)]
    left = np.flatnonzero(np.bincount(held, minlength=len(index.texts)) >= index.bound)
    if not len(left):
        return
    hits = np.bincount(held, np.repeat(often, count), len(index.texts))[left]
    dense = hits > DENSE * len(chars)
    for j in left[dense].tolist():
        yield j, 0, len(chars)
    left, hits = left[~dense], hits[~dense]
    if not len(left):
        return
    # only q-grams of windows still in question are spread out again, so many windows at a time as HITS allows
    turn = np.cumsum(hits) // HITS
    for t in np.unique(turn).tolist():
        some = left[turn == t]
        wanted = np.zeros(len(index.texts), bool)
        wanted[some] = True
        useful = grams[np.bincount(np.repeat(np.arange(len(grams)), count), wanted[held], len(grams)) > 0]
        keep = np.isin(place, useful)
        for j, spans in _bands(index, some, at[keep], place[keep], len(chars)).items():
            for a, b in _joined(spans):
                yield j, a, b


def matches(index: Index, text: str) -> list[tuple[int, int, int, int]]:
    """(item, from, to, edits) of the verified regions of a text, in its own code points, each item's merged."""
    chars, at = normal(text)
    found: dict[int, list[tuple[int, int, int]]] = {}
    overlap = 2 * index.longest
    for base in range(0, max(1, len(chars) - overlap), SEGMENT - overlap):
        segment = chars[base : base + SEGMENT]
        for j, a, b in regions(index, segment):
            k, size = int(index.edits[j]), len(index.texts[j])
            row = end_edits(index.texts[j], segment[a:b], k)
            if row is None:
                continue
            ends = np.flatnonzero(row <= k)
            cuts = np.flatnonzero(np.diff(ends) > size)
            for i, e in zip(np.concatenate([[0], cuts + 1]).tolist(), np.append(cuts, len(ends) - 1).tolist(), strict=True):
                lo, hi = base + a + max(0, int(ends[i]) - size - k), base + a + int(ends[e])
                span = int(at[lo]), int(at[hi - 1]) + 1, int(row[ends[i] : ends[e] + 1].min())
                for item in index.items[j]:
                    found.setdefault(item, []).append(span)
    out = []
    for item, spans in found.items():
        spans.sort()
        a, b, e = spans[0]
        for x, y, z in spans[1:]:
            if x <= b:
                b, e = max(b, y), min(e, z)
            else:
                out.append((item, a, b, e))
                a, b, e = x, y, z
        out.append((item, a, b, e))
    return sorted(out, key=lambda r: (r[1], r[0]))


MATCHES = "item_id bigint, start int, end int, edits int"


def _passes(benchmark: DataFrame, most: int) -> Iterator[list[tuple[int, str]]]:
    """The benchmark in parts of at most ``most`` characters or one item, by hash of the item."""
    rows = benchmark.selectExpr("cast(item_id as bigint) item_id", "text").where("item_id is not null and text is not null")
    total = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    parts = max(1, -(-int(total * 1.25) // most)) if total > most else 1
    for part in range(parts):
        found = rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == part).collect()
        yield sorted({(r["item_id"], r["text"]) for r in found})


def contaminated(docs: DataFrame, benchmark: DataFrame, *, most: int = PASS_CHARS, keep: list[str] | None = None) -> DataFrame:
    """A row for each region of a document that matches a benchmark item: ``keep`` (``doc_id``) and MATCHES.

    Texts are compared in lower case with white space collapsed; offsets are code points of the
    original; a region may be longer than its match by the edits allowed. Null and empty texts, null items
    and items shorter than a q-gram match nothing; repeated rows match alike; empty tables give no rows;
    other columns of either table are left out but those in ``keep``. The benchmark is held by every task in passes of at
    most ``most`` characters, so its size sets the number of passes, not the memory.
    """
    spark = docs.sparkSession
    keep = keep or ["doc_id"]
    rows = docs.select(*keep, F.col("text").alias("_text")).where(F.length("_text") >= Q)
    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1]]

    def one(part: list[tuple[int, str]]) -> DataFrame:
        sent = spark.sparkContext.broadcast(build_index(part))

        @frugal
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = sent.value
            for batch in batches:
                for rows in text_slices(batch, "_text"):
                    owner, found = [], []
                    for j, text in enumerate(rows.column(rows.num_columns - 1).to_pylist()):
                        hit = matches(index, text)
                        owner += [j] * len(hit)
                        found += hit
                    if found:
                        columns = [pa.array(v, t) for v, t in zip(zip(*found, strict=True), (pa.int64(), pa.int32(), pa.int32(), pa.int32()), strict=True)]
                        yield pa.RecordBatch.from_arrays([*(c.take(pa.array(owner)) for c in rows.columns[:-1]), *columns], names=[*keep, "item_id", "start", "end", "edits"])

        return rows.mapInArrow(run, ", ".join([*kinds, MATCHES]))

    out = None
    for part in _passes(benchmark, most):
        found = one(part)
        out = found if out is None else out.unionByName(found)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, *, most: int = PASS_CHARS) -> DataFrame:
    """The documents without a match, with all their columns, whatever their names.

    Each pass filters rows where they lie. Null and empty texts match nothing and stay; repeated rows stay or
    go alike; an empty table gives no rows, and an empty benchmark drops none.
    """
    spark, names = docs.sparkSession, docs.columns
    place = names.index("text")
    rows = docs.toDF(*[f"c{i}" for i in range(len(names))])
    for part in _passes(benchmark, most):
        sent = spark.sparkContext.broadcast(build_index(part))

        @frugal
        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for some in text_slices(batch, f"c{place}"):
                    clean = [not matches(sent.value, t) if t else True for t in some.column(place).to_pylist()]
                    yield some.filter(pa.array(clean, pa.bool_()))

        rows = rows.mapInArrow(run, rows.schema)
    return rows.toDF(*names)
