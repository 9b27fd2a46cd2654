"""Plain versions of the methods for tests; never imported by the library."""

from __future__ import annotations

import itertools

import numpy as np


def frequent(rows: list[tuple[int, int]], least: int) -> dict[int, int]:
    """(mask, weight) rows -> support of every frequent set."""
    out: dict[int, int] = {}
    for m, w in rows:
        bits = [b for b in range(63) if m >> b & 1]
        for r in range(1, len(bits) + 1):
            for c in itertools.combinations(bits, r):
                s = sum(1 << b for b in c)
                out[s] = out.get(s, 0) + w
    return {s: c for s, c in out.items() if c >= least}


def ward(x: np.ndarray) -> list[tuple[int, int, float, int]]:
    """Merges (least leaf, least leaf, height, size) by the increase of the within sum of squares."""
    sse = lambda rows: float(((x[rows] - x[rows].mean(0)) ** 2).sum())
    parts, out = {i: [i] for i in range(len(x))}, []
    while len(parts) > 1:
        best = min(((round(sse(parts[a] + parts[b]) - sse(parts[a]) - sse(parts[b]), 12), a, b) for a, b in itertools.combinations(sorted(parts), 2)))
        _, a, b = best
        inc = sse(parts[a] + parts[b]) - sse(parts[a]) - sse(parts[b])
        parts[a] = parts[a] + parts.pop(b)
        out.append((a, b, (2 * max(inc, 0)) ** 0.5, len(parts[a])))
    return out


def silhouette(d: np.ndarray, u: np.ndarray) -> float:
    out = []
    for i in range(len(u)):
        own = [d[i, j] for j in range(len(u)) if u[j] == u[i] and j != i]
        if not own:
            out.append(0.0)
            continue
        a, b = np.mean(own), min(np.mean([d[i, j] for j in range(len(u)) if u[j] == c]) for c in set(u) if c != u[i])
        out.append((b - a) / max(a, b))
    return float(np.mean(out))


def rand_index(u: np.ndarray, v: np.ndarray) -> float:
    """Adjusted, by counting pairs."""
    pairs = list(itertools.combinations(range(len(u)), 2))
    both = sum(u[i] == u[j] and v[i] == v[j] for i, j in pairs)
    su, sv, n = sum(u[i] == u[j] for i, j in pairs), sum(v[i] == v[j] for i, j in pairs), len(pairs)
    low, top = su * sv / n, (su + sv) / 2
    return 1.0 if top == low else (both - low) / (top - low)
