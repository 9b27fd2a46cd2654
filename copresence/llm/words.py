"""Words and shingles of whole texts as 64-bit numbers, in numpy.

A word is a lower-case run without white space. Its number is a polynomial over its bytes (each byte by a random 64-bit
value) taken from running sums, so a batch of texts is handled in a few passes over its bytes.
"""

from __future__ import annotations

import re

import numpy as np

SHINGLE = 5
MIX1, MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
STEP = np.uint64(0x9E3779B97F4A7C15)
BLOCK = 1 << 18  # bytes handled at once
_MASK = (1 << 64) - 1
_BASE = 0x5851F42D4C957F2D  # odd, so it has an inverse modulo 2**64
_VALUE = np.random.default_rng(20240501).integers(0, 1 << 64, 256, np.uint64)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 28, 29, 30, 31, 32]] = True
_EDGE = re.compile(rb"[\x09-\x0d\x1c-\x20]")
_WIDE_SPACE = re.compile("[\x85\xa0  -     　]")
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def words(text: str | None) -> list[str]:
    return (text or "").lower().split()


def mix(x: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit numbers (a bijection)."""
    x = (x ^ (x >> np.uint64(30))) * MIX1
    x = (x ^ (x >> np.uint64(27))) * MIX2
    return x ^ (x >> np.uint64(31))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, at least n of each."""
    if len(_powers[0]) < n:
        size = 1 << max(n, BLOCK).bit_length()
        for k, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            table = np.full(size, base & _MASK, np.uint64)
            table[0] = 1
            _powers[k] = np.multiply.accumulate(table)
    return _powers[0], _powers[1]


def _raw(text: str | None) -> bytes:
    t = (text or "").lower()
    if not t.isascii():
        t = _WIDE_SPACE.sub(" ", t)
    return t.encode("utf-8", "surrogatepass")


def _hash_block(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    data = np.frombuffer(b"\n".join([*raw, b""]), np.uint8)
    space = _SPACE[data]
    edge = np.flatnonzero(space[1:] != space[:-1]) + 1  # the last byte is a space
    if not space[0]:
        edge = np.concatenate([[0], edge])
    first, last = edge[0::2], edge[1::2]
    power, inverse = _power_tables(len(data))
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_VALUE[data] * power[: len(data)], out=sums[1:])
    hashes = mix((sums[last] - sums[first]) * inverse[first] + (last - first).astype(np.uint64))
    ends = np.cumsum([len(r) + 1 for r in raw])
    upto = np.searchsorted(first, ends)
    tails = data[last - 1].astype(np.uint16) << 8 | data[np.maximum(last - 2, first)]
    return hashes, np.diff(np.concatenate([[0], upto])), tails


def _pieces(raw: bytes) -> list[bytes]:
    """A long text in pieces of about BLOCK bytes that end at white space, so that what is held at once is bounded."""
    out, at = [], 0
    while len(raw) - at > 2 * BLOCK and (edge := _EDGE.search(raw, at + BLOCK)):
        out.append(raw[at : edge.end()])
        at = edge.end()
    return [*out, raw[at:]]


def hash_words(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers of all words of all texts in a row, how many each text has, and the last two bytes of each word."""
    parts, held, owner, size = [], [], [], 0
    for k, t in enumerate(texts):
        for piece in _pieces(_raw(t)):
            held.append(piece)
            owner.append(k)
            size += len(piece)
            if size >= BLOCK:
                parts.append(_hash_block(held))
                held, size = [], 0
    if held:
        parts.append(_hash_block(held))
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.uint16)
    hashes, counts, tails = (np.concatenate(x) for x in zip(*parts, strict=True))
    return hashes, np.bincount(owner, counts, len(texts)).astype(np.int64), tails


def hash_texts(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of all words of all texts in a row, and how many each text has."""
    return hash_words(texts)[:2]


def text_hashes(text: str | None) -> np.ndarray:
    return hash_texts([text])[0]


def shingles(hashes: np.ndarray, n: int = SHINGLE) -> np.ndarray:
    """A number for each run of n words; a text of fewer words (but some) is one shingle."""
    if not len(hashes):
        return hashes
    if len(hashes) < n:
        hashes = np.concatenate([hashes, np.full(n - len(hashes), 7, np.uint64)])
    out = np.zeros(len(hashes) - n + 1, np.uint64)
    for k in range(n):
        out = (out ^ hashes[k : len(hashes) - n + 1 + k]) * MIX1
        out ^= out >> np.uint64(29)
    return mix(out)


def weighted_similarity(a: np.ndarray, b: np.ndarray) -> float:
    """Sum of least over sum of greatest multiplicities of two arrays' values; 0 if both are empty."""
    if not len(a) and not len(b):
        return 0.0
    x, nx = np.unique(a, return_counts=True)
    y, ny = np.unique(b, return_counts=True)
    _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
    low = int(np.minimum(nx[i], ny[j]).sum())
    return low / (len(a) + len(b) - low)
