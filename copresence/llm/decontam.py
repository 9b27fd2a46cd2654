"""Benchmark passages in documents: fingerprints of item-sized windows, a Hamming index, an exact check.

A window's SimHash has, for each of 64 bits, the majority among the digests of its word pairs. For every word position
of a document and every window size in use, the fingerprint is computed exactly: bit counts are kept as bit planes and
added by doubling (a window of 2n is two of n), so a position costs a few dozen word operations a size, whatever the
size is.

An item of n words is looked for by a window of its own size: its words but the c at either end that may be changed in
a place `least` alike to it (c shingles in all, a ninth of them at 0.8), rounded down to four leading bits. Under five
such shingles, a place that is alike has these words unchanged, since a change further in alters more shingles than
may be. From five on, up to c / 5 changes lie inside: about a tenth of the fingerprint's bits flip, and RADIUS holds
them in about 19 of 20 places. For the rest, runs inside the item are indexed too, so many and so far apart (four
words, thus no shingle in common) that c shingles can't alter them all; one is found unchanged.

The index cuts a fingerprint into four blocks and stores every value within a fourth of the radius of a window's block.
If two fingerprints differ in at most radius bits, some block differs in at most a fourth of them, so every window
within the radius is found. A window found gives the places at which the item may start, which are all compared
exactly: the item against as many words of the document, by weighted similarity of five-word shingles, `least` or more.

The items are the stated query set; they go to all tasks in blocks bounded in number and bytes (checked), one scan of
the documents a block. Documents are read once a block and never shuffled.

Defined cases: null and empty texts hold nothing; items under five words are found where their very words stand (give
`least_words` to leave them out); items without words are not looked for; equal items are found each under its id; a
passage met more than once in a document is reported at its best, then first place; repeated rows are reported each;
null ids are kept; extra columns are kept by `drop_contaminated`.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copresence.ship import arrow_map

from .common import whole
from .words import MIX1, SHINGLE, hash_texts, mix, shingles, text_hashes

SIMILARITY = 0.8
LOOSEST = 0.6  # below, what may be changed leaves no window
PARTS = 4  # blocks of a fingerprint, 16 bits each
RADIUS = 11  # of windows that may hold changes
EXACT = PARTS - 1  # radius of windows without changes: some block is the very same
MAX_ITEMS = 20_000
MAX_BYTES = 16 << 20  # of the items that go to a task at once
BLOCK = 1 << 14  # positions handled at once
TEXT_BYTES = 4 << 20  # of the texts searched at once, unless one alone is longer

Planes = list[np.ndarray]


def pair_hashes(h: np.ndarray) -> np.ndarray:
    """A digest of each two neighbouring words."""
    return mix((h[:-1] * MIX1) ^ (h[1:] >> np.uint64(7)) ^ h[1:]) if len(h) > 1 else np.zeros(0, np.uint64)


def _add(a: Planes, b: Planes) -> Planes:
    """Sum of two numbers a bit position, as planes from the lowest bit up."""
    out, carry = [], None
    for i in range(max(len(a), len(b))):
        x, y = (a[i] if i < len(a) else None), (b[i] if i < len(b) else None)
        if x is None or y is None:
            x, y = (y if x is None else x), carry
            out.append(x if y is None else x ^ y)
            carry = None if y is None else x & y
        elif carry is None:
            out.append(x ^ y)
            carry = x & y
        else:
            half = x ^ y
            out.append(half ^ carry)
            carry = (x & y) | (half & carry)
    return out if carry is None else [*out, carry]


def _majority(planes: Planes, size: int) -> np.ndarray:
    """Bits whose count is over half of size."""
    more, level = np.zeros_like(planes[0]), ~np.zeros_like(planes[0])
    for k in range(len(planes) - 1, -1, -1):
        if (size // 2) >> k & 1:
            level &= planes[k]
        else:
            more |= level & planes[k]
            level &= ~planes[k]
    return more


def _halves(n: int) -> tuple[int, int]:
    high = 1 << (n.bit_length() - 1)
    return (n // 2, n // 2) if n == high else (high, n - high)


def fingerprints(pairs: np.ndarray, sizes: list[int]) -> Iterator[tuple[int, np.ndarray]]:
    """Each size, in rising order, with the fingerprint at each position where a window of that many pairs fits."""
    sizes = sorted(n for n in sizes if n <= len(pairs))
    needed, grown = set(sizes), list(sizes)
    while grown:
        grown = [m for n in grown if n > 1 for m in _halves(n) if m not in needed]
        needed.update(grown)
    last = {m: n for n in sorted(needed) if n > 1 for m in _halves(n)}  # the greatest size that a sum is part of
    sums: dict[int, Planes] = {}
    for n in sorted(needed):
        if n == 1:
            sums[n] = [pairs]
        else:
            one, two = _halves(n)
            keep = len(pairs) - n + 1
            sums[n] = _add([p[:keep] for p in sums[one]], [p[one : one + keep] for p in sums[two]])
            for m in {one, two}:
                if last[m] == n:
                    del sums[m]
        if n in sizes:
            yield n, _majority(sums[n], n)
        if n not in last:
            sums.pop(n, None)


def allowed(n: int, least: float) -> int:
    """How many shingles of n words may differ at a similarity of `least`."""
    return int((n - SHINGLE + 1) * (1 - least) / (1 + least) + 1e-9)


def rounded(n: int) -> int:
    """n with all but its four leading bits cleared."""
    drop = max(0, n.bit_length() - 4)
    return n >> drop << drop


def windows_of(n: int, least: float) -> list[tuple[int, int, int]]:
    """(first word, pairs, radius) of the windows by which an item of n words, five or more, is looked for."""
    c = allowed(n, least)
    core = n - 2 * c
    size = rounded(core - 1)
    out = [(c + (core - 1 - size) // 2, size, RADIUS if c >= SHINGLE else EXACT)]
    if c >= SHINGLE:
        gap, runs = SHINGLE - 1, c // (SHINGLE - 1) + 1
        run = (core - gap * (runs - 1)) // runs
        out += [(c + k * (run + gap), rounded(run - 1), EXACT) for k in range(runs)]
    return out


@dataclass
class Item:
    item_id: int | None
    words: int
    slack: int  # places to either side at which it may start
    values: np.ndarray  # distinct shingles
    counts: list[int]

    def best(self, words_of: np.ndarray, starts: int) -> tuple[float, int]:
        """The greatest similarity to as many of these words, and its first start out of so many."""
        own = shingles(words_of)
        m = sum(self.counts)
        at = np.minimum(np.searchsorted(self.values, own), len(self.values) - 1)
        ids = np.where(self.values[at] == own, at, -1).tolist()
        held, common, right, found = [0] * len(self.values), 0, 0, (0.0, 0)
        for s in range(min(starts, len(ids))):
            while right < min(s + m, len(ids)):
                i, right = ids[right], right + 1
                if i >= 0:
                    held[i] += 1
                    common += held[i] <= self.counts[i]
            alike = common / (m + right - s - common)
            if alike > found[0]:
                found = alike, s
            if (i := ids[s]) >= 0:
                common -= held[i] <= self.counts[i]
                held[i] -= 1
        return found


class Blocks:
    """Windows of one size and radius by the blocks of their fingerprints."""

    def __init__(self, prints: np.ndarray, radius: int):
        self.prints, self.radius, self.tables = prints, radius, []
        flips = np.array([sum(1 << b for b in c) for m in range(radius // PARTS + 1) for c in itertools.combinations(range(16), m)], np.int64)
        for k in range(PARTS):
            values = (self.cut(prints, k).astype(np.int64)[:, None] ^ flips).ravel()
            order = np.argsort(values, kind="stable")
            first = np.searchsorted(values[order], np.arange(65537))
            self.tables.append((first[1:] > first[:-1], first, (order // len(flips)).astype(np.int32)))

    @staticmethod
    def cut(prints: np.ndarray, k: int) -> np.ndarray:
        return np.ascontiguousarray(prints).view(np.uint16)[k::PARTS]

    def near(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions and windows whose fingerprints differ in at most radius bits."""
        found = []
        for k, (known, first, window) in enumerate(self.tables):
            own = self.cut(prints, k)
            hit = np.flatnonzero(known[own])
            low = first[own[hit]]
            n = first[own[hit].astype(np.int64) + 1] - low
            place = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(n.sum())
            p, w = np.repeat(hit, n), window[place]
            keep = np.flatnonzero(np.bitwise_count(prints[p] ^ self.prints[w]) <= self.radius)
            found.append(p[keep] * len(self.prints) + w[keep])
        return np.divmod(np.unique(np.concatenate(found)), len(self.prints))


class Index:
    """Items by the fingerprints of their windows, and those under five words by their words."""

    def __init__(self, rows: list[tuple[int | None, str | None]], least: float = SIMILARITY, least_words: int = 1):
        if not LOOSEST <= least <= 1:
            raise ValueError(f"similarity must be from {LOOSEST} to 1")
        self.least, self.items = least, []
        self.short: dict[int, dict[int, list[int]]] = {}  # words: {number of their run: items}
        found: dict[tuple[int, int], list[tuple[int, int, int]]] = {}  # size, radius: (fingerprint, item, first word)
        for item_id, text in rows:
            h = text_hashes(text)
            if len(h) < max(1, least_words):
                continue
            if len(h) < SHINGLE:
                self.short.setdefault(len(h), {}).setdefault(int(shingles(h, len(h))[0]), []).append(len(self.items))
            else:
                windows = windows_of(len(h), least)
                prints = dict(fingerprints(pair_hashes(h), [size for _, size, _ in windows]))
                for first, size, radius in windows:
                    found.setdefault((size, radius), []).append((int(prints[size][first]), len(self.items), first))
            values, counts = np.unique(shingles(h), return_counts=True)
            self.items.append(Item(item_id, len(h), allowed(len(h), least), values, counts.tolist()))
        self.groups: dict[int, list[tuple[Blocks, np.ndarray, np.ndarray]]] = {}
        for (size, radius), rows_of in sorted(found.items()):
            prints, owner, first = zip(*rows_of, strict=True)
            self.groups.setdefault(size, []).append((Blocks(np.array(prints, np.uint64), radius), np.array(owner), np.array(first)))

    def _places(self, flat: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> set[tuple[int, int, int]]:
        """(text, item, word at which it would start) of all windows that are near."""
        out: set[tuple[int, int, int]] = set()
        pairs, sizes = pair_hashes(flat), list(self.groups)
        for first in range(0, len(pairs) if sizes else 0, BLOCK):
            for size, prints in fingerprints(pairs[first : first + BLOCK + sizes[-1]], sizes):
                for blocks, owner, offset in self.groups[size]:
                    at, which = blocks.near(prints[:BLOCK])
                    text = np.searchsorted(ends, at + first, "right")
                    inside = np.flatnonzero(at + first + size < ends[text])  # else the window runs into the next text
                    start = at[inside] + first - starts[text[inside]] - offset[which[inside]]
                    out.update(zip(text[inside].tolist(), owner[which[inside]].tolist(), start.tolist(), strict=True))
        return out

    def search(self, texts: list[str | None]) -> list[tuple[int, int, float, int]]:
        """(text number, item number, similarity, first word) for each text and item that it holds, the best place."""
        flat, counts = hash_texts(texts)
        if not len(flat):
            return []
        ends = np.cumsum(counts)
        starts = ends - counts
        best: dict[tuple[int, int], tuple[float, int]] = {}
        for text, item, start in self._places(flat, starts, ends):
            own = self.items[item]
            low, high = max(0, start - own.slack), min(start + own.slack, int(counts[text]) - 1)
            if low <= high:
                words_of = flat[starts[text] + low : min(starts[text] + high + own.words, ends[text])]
                alike, at = own.best(words_of, high - low + 1)
                if alike >= self.least:
                    best[text, item] = max(best.get((text, item), (0.0, 0)), (alike, -low - at))
        for n, known in self.short.items():
            runs = shingles(flat, n) if len(flat) >= n else flat[:0]
            hit = np.flatnonzero(np.isin(runs, np.array(list(known), np.uint64)))
            text = np.searchsorted(ends, hit, "right")
            for at, t in zip(hit.tolist(), text.tolist(), strict=True):
                if at + n <= ends[t]:
                    for item in known[int(runs[at])]:
                        best.setdefault((t, item), (1.0, int(starts[t]) - at))
        return [(t, i, s, -start) for (t, i), (s, start) in sorted(best.items())]


_ready: dict[int, Index] = {}


def _index(rows: list[tuple[int | None, str | None]], least: float, least_words: int) -> Index:
    """The index of a block of items, made once a worker."""
    key = hash((tuple(rows), least, least_words))
    if key not in _ready:
        _ready.clear()
        _ready[key] = Index(rows, least, least_words)
    return _ready[key]


def _blocks(benchmark: DataFrame, at_once: int) -> Iterator[list[tuple[int | None, str | None]]]:
    """The query set in blocks of at most about at_once items and MAX_BYTES; a greater one raises."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), whole("text").alias("text"))
    size = items.agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("text")).alias("bytes")).first()
    over = max(size["n"] / at_once, (size["bytes"] or 0) / MAX_BYTES)
    n = math.ceil(2 * over) if over > 1 else 1
    for k in range(n):
        part = items if n == 1 else items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)
        if n > 1 and part.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0] > 4 * MAX_BYTES:
            raise ValueError(f"benchmark items of more than {4 * MAX_BYTES} bytes can't be sent to a task")
        yield [(r["item_id"], r["text"]) for r in part.collect()]


def _slices(batch: pa.RecordBatch, column: int) -> Iterator[pa.RecordBatch]:
    """The batch in slices of about TEXT_BYTES of text at most."""
    sizes = np.array([len(t.as_buffer()) if t.is_valid else 0 for t in batch.column(column)], np.int64)
    group = (np.cumsum(sizes) - sizes) // TEXT_BYTES
    edges = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(sizes)] if len(sizes) else []
    for a, z in itertools.pairwise(edges):
        yield batch.slice(a, z - a)


FOUND = "doc_id long, item_id long, similarity double, first_word long, n_words long"


def contaminated(docs: DataFrame, benchmark: DataFrame, least: float = SIMILARITY, at_once: int = MAX_ITEMS, least_words: int = 1) -> DataFrame:
    """A row for each document and item that it holds: doc_id, item_id, similarity, first_word, n_words (the item's)."""

    def of(rows: list[tuple[int | None, str | None]]) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = _index(rows, least, least_words)
            for part in (p for b in batches for p in _slices(b, 1)):
                got = index.search(part.column(1).to_pylist())
                if got:
                    texts, items, alike, first = zip(*got, strict=True)
                    columns = [
                        part.column(0).take(pa.array(texts)), pa.array([index.items[i].item_id for i in items], pa.int64()), pa.array(alike, pa.float64()),
                        pa.array(first, pa.int64()), pa.array([index.items[i].words for i in items], pa.int64()),
                    ]
                    yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "item_id", "similarity", "first_word", "n_words"])

        return arrow_map(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, FOUND)

    parts = [of(rows) for rows in _blocks(benchmark, at_once)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, least: float = SIMILARITY, at_once: int = MAX_ITEMS, least_words: int = 1) -> DataFrame:
    """docs without the rows that hold an item; one scan a block of items."""
    at = docs.columns.index("text")

    def keep(rows: list[tuple[int | None, str | None]]):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = _index(rows, least, least_words)
            for part in (p for b in batches for p in _slices(b, at)):
                bad = {g[0] for g in index.search(part.column(at).to_pylist())}
                yield part.filter(pa.array([i not in bad for i in range(part.num_rows)], pa.bool_())) if bad else part

        return run

    for rows in _blocks(benchmark, at_once):
        docs = arrow_map(docs, keep(rows), docs.schema)
    return docs
