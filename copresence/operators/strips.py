"""Word strips by whole rows: the words of a text as intervals, what their buffers meet, and patterns, without a shuffle of words.

Words of a text are disjoint and in order, so the words that a buffer meets are next to it: the k-th ones on either side
for k = 1, 2, ... until none of a batch is within reach. All of it is arithmetic over the bytes of a batch of texts.

Texts that share an id are dealt by it: words with the same number are one place of the id and end where they end together
(`place_masks`), so what a place meets follows from the few places on either side, however many texts there are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from copresence.ship import arrow_map

IDS = 1_000_000  # word numbers that an id of a text leaves room for
BYTES = 4 << 20  # texts handled at once, unless one is longer
BITS = 27
SPACE = np.isin(np.arange(256), list(b" \t\n\x0b\f\r"))
LETTER = np.array([b - 96 if 97 <= b <= 122 else b - 64 if 65 <= b <= 90 else 0 for b in range(256)], np.int64)

UNITS = "grp string, part long, unit_id long, lo long, hi long, bit int"
TX = "grp string, unit_id long, mask long"
PATTERNS = "grp string, mask long, weight long"


def words(data: np.ndarray, offsets: np.ndarray, core: bool) -> tuple[np.ndarray, ...]:
    """row, number, lo, hi, bit of each word of texts that lie one after the other in `data`. core: of the middle half only."""
    solid = ~SPACE[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[offsets] = True
    begins, ends = solid.copy(), solid.copy()
    begins[1:] &= ~solid[:-1] | edge[1:-1]
    ends[:-1] &= ~solid[1:] | edge[1:-1]
    begins, ends = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    chars = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])  # bytes that go on with a character don't count
    size = chars[ends] - chars[begins]
    row = np.searchsorted(offsets, begins, "right") - 1
    n = np.bincount(row, minlength=len(offsets) - 1)
    first = np.cumsum(n) - n
    upto = np.concatenate([[0], np.cumsum(size + 1)])
    number, lo = np.arange(len(row)) - first[row], upto[:-1] - upto[first[row]]
    out = (row, number, lo, lo + size, LETTER[data[begins]])
    if core:
        middle = (number * 4 >= n[row]) & (number * 4 < 3 * n[row])
        out = tuple(x[middle] for x in out)
    return out


def row_masks(row: np.ndarray, lo: np.ndarray, hi: np.ndarray, bit: np.ndarray, d: int) -> np.ndarray:
    """Classes of each word and of the words of its row within d."""
    own = np.left_shift(1, bit)
    mask = own.copy()
    for k in range(1, len(row)):
        met = (lo[k:] - hi[:-k] <= d) & (row[k:] == row[:-k])
        if not met.any():
            break
        mask[:-k] |= own[k:] * met
        mask[k:] |= own[:-k] * met
    return mask


def _slices(texts: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """First row, bytes and offsets of runs of texts of about BYTES together."""
    t = texts.cast(pa.large_string()).fill_null("")
    if isinstance(t, pa.ChunkedArray):
        t = t.combine_chunks()
    at = np.frombuffer(t.buffers()[1], np.int64)[t.offset : t.offset + len(t) + 1]
    data = np.frombuffer(t.buffers()[2] or b"", np.uint8)
    first = 0
    while first < len(t):
        end = max(first + 1, int(np.searchsorted(at, at[first] + BYTES, "right")) - 1)
        yield first, data[at[first] : at[end]], at[first : end + 1] - at[first]
        first = end


def _by_rows(docs: DataFrame, schema: str, make) -> DataFrame:
    """docs(doc_id, grp, text): make(ids, groups, row, number, lo, hi, bit) gives the columns for a run of texts."""
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, groups = b.column(0).to_numpy(zero_copy_only=False), b.column(1)
            for first, data, offsets in _slices(b.column(2)):
                end = first + len(offsets) - 1
                columns = make(ids[first:end], groups.slice(first, end - first), data, offsets)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=names)

    return arrow_map(docs.select("doc_id", "grp", "text"), run, schema)


def units(docs: DataFrame, core: bool = False) -> DataFrame:
    """docs(doc_id, grp, text), no id null or repeated -> SPAN units."""

    def make(ids, groups, data, offsets):
        row, number, lo, hi, bit = words(data, offsets, core)
        return groups.take(pa.array(row)), ids[row], ids[row] * IDS + number, lo, hi, bit.astype(np.int32)

    return _by_rows(docs, UNITS, make)


def transactions(docs: DataFrame, d: int, core: bool = False) -> DataFrame:
    """The same rows' transactions: what `buffer_span` gives for `units`."""

    def make(ids, groups, data, offsets):
        row, number, lo, hi, bit = words(data, offsets, core)
        return groups.take(pa.array(row)), ids[row] * IDS + number, row_masks(row, lo, hi, bit, d)

    return _by_rows(docs, TX, make)


def patterns(docs: DataFrame, d: int, core: bool = False) -> DataFrame:
    """Patterns of these transactions, counted in each run of texts; to be added up by group and mask."""

    def make(ids, groups, data, offsets):
        row, _, lo, hi, bit = words(data, offsets, core)
        book = groups.dictionary_encode()
        group = book.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        key, weight = np.unique(group[row] << BITS | row_masks(row, lo, hi, bit, d), return_counts=True)
        return book.dictionary.take(pa.array(key >> BITS)), key & ((1 << BITS) - 1), weight

    return _by_rows(docs, PATTERNS, make)


# ---- texts that share an id


def place_masks(ids: np.ndarray, group: np.ndarray, texts: pa.Array, d: int, core: bool) -> tuple[np.ndarray, ...]:
    """group, id, number and mask of each place of each group; `ids` are in order and each has all of its texts here.

    A word is met by another place as far as its own length reaches back, and the words of a place all end where its
    lengths, added to those before, end: so words are asked by place, and only for the d / 2 + 1 places on either side."""
    found = [(first + w[0], w[1], w[3] - w[2], w[4]) for first, data, offsets in _slices(texts) for w in [words(data, offsets, False)]]
    row, number, size, bit = map(np.concatenate, zip(*found, strict=True))
    known, own = np.unique(ids, return_inverse=True)
    places = np.zeros(len(known), np.int64)
    np.maximum.at(places, own[row], number + 1)
    base = np.cumsum(places) - places
    of = np.repeat(np.arange(len(known)), places)
    place = base[own[row]] + number
    end = np.cumsum(np.bincount(place, size + 1, len(of)).astype(np.int64))
    if core:
        n = np.bincount(row, minlength=len(ids))[row]
        middle = (number * 4 >= n) & (number * 4 < 3 * n)
        row, place, size, bit = (x[middle] for x in (row, place, size, bit))
    order = np.lexsort((place, group[row]))
    unit_group, unit_place, reach = group[row][order], place[order], size[order]
    first = np.flatnonzero(np.diff(unit_place, prepend=-1) | np.diff(unit_group, prepend=-1))
    if not len(first):
        return (np.zeros(0, np.int64),) * 4
    unit_group, unit_place, reach = unit_group[first], unit_place[first], np.maximum.reduceat(reach, first)
    order = np.argsort(place, kind="stable")
    place, size, bit = place[order], size[order], np.left_shift(1, bit[order])

    def folded(at: np.ndarray, bits: np.ndarray) -> np.ndarray:
        """Bits by place; `at` is in order."""
        out = np.zeros(len(of), np.int64)
        if len(at):
            starts = np.flatnonzero(np.diff(at, prepend=-1))
            out[at[starts]] = np.bitwise_or.reduceat(bits, starts)
        return out

    def near(q: np.ndarray, length: np.ndarray, k: int) -> np.ndarray:
        """Whether words of these lengths at the places q reach back to what ends k places before."""
        p = np.maximum(q - k, 0)
        return (q >= k) & (of[p] == of[q]) & (end[q] - end[p] - d <= length)

    held = folded(place, bit)
    met = held.copy()
    mask = np.zeros(len(unit_place), np.int64)
    for k in range(1, d // 2 + 2):
        back = near(place, size, k)
        met |= folded(place[back] - k, bit[back])
        back = near(unit_place, reach, k)
        mask[back] |= held[unit_place[back] - k]
    return unit_group, known[of[unit_place]], unit_place - base[of[unit_place]], mask | met[unit_place]


def _whole_ids(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, pa.Array, pa.Array]]:
    """ids, groups and texts, about BYTES of them together, of rows in the order of their ids; no id is cut."""
    held: list[pa.RecordBatch] = []

    def pieces(whole: list[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, pa.Array, pa.Array]]:
        t = pa.Table.from_batches(whole).combine_chunks() if whole else None
        if not t:
            return
        ids, groups, texts = (c.chunk(0) for c in t.columns)
        ids, texts = ids.to_numpy(zero_copy_only=False).astype(np.int64), texts.cast(pa.large_string())
        upto = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False))
        last = np.flatnonzero(np.diff(ids, append=ids[-1] + 1)) + 1
        begin = 0
        while begin < len(ids):
            k = np.searchsorted(upto[last - 1], (upto[begin - 1] if begin else 0) + BYTES, "right") - 1
            end = int(last[max(k, np.searchsorted(last, begin, "right"))])
            yield ids[begin:end], groups.slice(begin, end - begin), texts.slice(begin, end - begin)
            begin = end

    for b in batches:
        if not b.num_rows:
            continue
        ids = b.column(0).to_numpy(zero_copy_only=False)
        start = int(np.searchsorted(ids, ids[-1]))
        if start or (held and held[0].column(0)[0].as_py() != ids[-1]):
            yield from pieces([*held, b.slice(0, start)])
            held = []
        held.append(b.slice(start))
    yield from pieces(held)


def _by_id(docs: DataFrame, schema: str, d: int, core: bool, make) -> DataFrame:
    """docs(doc_id, grp, text), no id null: make(groups, group, id, number, mask) gives the columns for a run of ids."""
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, groups, texts in _whole_ids(batches):
            book = groups.dictionary_encode()
            found = place_masks(ids, book.indices.to_numpy(zero_copy_only=False).astype(np.int64), texts, d, core)
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in make(book.dictionary, *found)], names=names)

    return arrow_map(docs.select("doc_id", "grp", "text").repartition("doc_id").sortWithinPartitions("doc_id"), run, schema)


def transactions_by_id(docs: DataFrame, d: int, core: bool = False) -> DataFrame:
    return _by_id(docs, TX, d, core, lambda names, group, own, number, mask: (names.take(pa.array(group)), own * IDS + number, mask))


def patterns_by_id(docs: DataFrame, d: int, core: bool = False) -> DataFrame:
    """Patterns of these transactions, counted in each run of ids."""

    def make(names, group, own, number, mask):
        key, weight = np.unique(group << BITS | mask, return_counts=True)
        return names.take(pa.array(key >> BITS)), key & ((1 << BITS) - 1), weight

    return _by_id(docs, PATTERNS, d, core, make)
