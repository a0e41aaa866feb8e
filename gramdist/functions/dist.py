"""Boundary-to-boundary shortest paths of a block, and their merging.

A block of p rows and q columns shares its border vertices with its neighbours, so it has p + q + 1 inputs and as
many outputs. Inputs: 0..p up the left column, p..p+q along the top row. Outputs: 0..q along the bottom row,
q..p+q up the right column. A path leads from i to j iff j <= q + i and i <= p + j; other entries hold a large
number that grows with the distance from that band, which keeps the matrix Monge.
"""

from __future__ import annotations

import numpy as np

from ..scoring import Scoring
from . import minima


def excess(p: int, q: int) -> np.ndarray:
    """How far each entry lies outside the band of real paths; 0 inside."""
    k = np.arange(p + q + 1)
    return np.maximum(np.maximum(k[None, :] - q - k[:, None], k[:, None] - p - k[None, :]), 0)


SMALL = 32
REACH = 1 << 24  # letters of a segment up to which big() holds


def big(scoring: Scoring):
    """More than any real path through a segment of up to REACH letters; dense matrices of longer ones don't fit any
    memory, and leaf() is the only place where a matrix starts."""
    return scoring.dtype(scoring.largest + 1) * scoring.dtype(4 * REACH)


def leaf(a: str, b: str, scoring: Scoring) -> np.ndarray:
    """One letter against one letter."""
    d, i, far = scoring.del_cost(a), scoring.ins_cost(b), big(scoring)
    return np.array([[0, i, far], [d, min(scoring.sub_cost(a, b), d + i), i], [far, d, 0]], scoring.dtype)


def by_tables(a: str, b: str, scoring: Scoring) -> np.ndarray:
    """From the prefix tables of every input vertex at once: one vector over inputs for each cell."""
    p, q = len(a), len(b)
    n = p + q + 1
    far = big(scoring)
    dels, ins = scoring.vectors(a, b)
    start = np.full((p + 1, q + 1, n), 4 * far * n, scoring.dtype)
    for i in range(p + 1):
        start[p - i, 0, i] = 0
    for i in range(p, n):
        start[0, i - p, i] = 0
    t = start
    for r in range(p + 1):
        for c in range(q + 1):
            if r:
                t[r, c] = np.minimum(t[r, c], t[r - 1, c] + dels[r - 1])
            if c:
                t[r, c] = np.minimum(t[r, c], t[r, c - 1] + ins[c - 1])
            if r and c:
                t[r, c] = np.minimum(t[r, c], t[r - 1, c - 1] + scoring.sub_cost(a[r - 1], b[c - 1]))
    out = np.empty((n, n), scoring.dtype)
    out[:, : q + 1] = t[p, :, :].T
    out[:, q:] = t[::-1, q, :].T
    e = excess(p, q)
    return np.where(e > 0, e * far, out)


def min_plus(x: np.ndarray, y: np.ndarray, method: str = "dense", probes: list | None = None) -> np.ndarray:
    """min over k of x[i, k] + y[k, j]; the other methods use that each row's minima move with the column, and monge
    that they move with the row too. Up to SMALL the monge form reads all, which is a constant more and faster."""
    if method == "monge" and min(y.shape[0], x.shape[0], y.shape[1]) > SMALL:
        return minima.monge_product(x, y, probes)
    if method in ("dense", "monge"):
        if probes is not None:
            probes.append(x.shape[0] * x.shape[1] * y.shape[1])
        out = x[:, :1] + y[:1, :]
        for k in range(1, y.shape[0]):
            np.minimum(out, x[:, k : k + 1] + y[k : k + 1, :], out=out)
        return out
    return np.stack([minima.column_minima(row, y, method, probes) for row in x])


def merge_columns(d1: np.ndarray, d2: np.ndarray, p: int, q1: int, q2: int, far, method: str = "monge", probes: list | None = None) -> np.ndarray:
    """Same rows, columns side by side: paths cross the shared column of p + 1 vertices."""
    n = p + q1 + q2 + 1
    out = np.empty((n, n), d1.dtype)
    cross = min_plus(d1[:, q1:], d2[: p + 1, :], method, probes)
    out[: p + q1 + 1, q1:] = cross
    out[: p + q1 + 1, : q1 + 1] = d1[:, : q1 + 1]
    out[p + q1 :, q1:] = d2[p:, :]
    return outside(out, p, q1 + q2, far)


def merge_rows(d1: np.ndarray, d2: np.ndarray, p1: int, p2: int, q: int, far, method: str = "monge", probes: list | None = None) -> np.ndarray:
    """Same columns, d1 above d2: paths cross the shared row of q + 1 vertices."""
    n = p1 + p2 + q + 1
    out = np.empty((n, n), d1.dtype)
    cross = min_plus(d1[:, : q + 1], d2[p2:, :], method, probes)
    out[p2:, : q + p2 + 1] = cross
    out[p2:, q + p2 :] = d1[:, q:]
    out[: p2 + 1, : q + p2 + 1] = d2[: p2 + 1, :]
    return outside(out, p1 + p2, q, far)


def outside(d: np.ndarray, p: int, q: int, far) -> np.ndarray:
    e = excess(p, q)
    np.copyto(d, (e * far).astype(d.dtype), where=e > 0)
    return d


def by_division(a: str, b: str, scoring: Scoring, method: str = "monge") -> np.ndarray:
    """Halve the longer string, build both parts, merge."""
    if len(a) == 1 and len(b) == 1:
        return leaf(a, b, scoring)
    far = big(scoring)
    if len(a) >= len(b):
        m = len(a) // 2
        return merge_rows(by_division(a[:m], b, scoring, method), by_division(a[m:], b, scoring, method), m, len(a) - m, len(b), far, method)
    m = len(b) // 2
    return merge_columns(by_division(a, b[:m], scoring, method), by_division(a, b[m:], scoring, method), len(a), m, len(b) - m, far, method)


def by_braid(a: str, b: str, scoring: Scoring) -> np.ndarray:
    """The square of the side in steps, for uniform costs: comb the braid letter by letter, then sum its points."""
    from . import succinct as S

    t = S.Linear.of_texts(a, b, scoring)
    return outside(t.dense(), len(a), len(b), big(scoring))


def by_increments(a: str, b: str, scoring: Scoring) -> np.ndarray:
    """Add the letters of b one column at a time, keeping for every input the column of values above it: x values an
    input a letter, so the cube of the side in all, in vectors over all inputs. Works for any costs."""
    p, q = len(a), len(b)
    n, far = p + q + 1, big(scoring)
    dels, ins = scoring.vectors(a, b)
    run = np.r_[np.zeros(1, dels.dtype), np.cumsum(dels)]
    col = np.full((n, p + 1), far * n * 4, scoring.dtype)  # [input, depth]
    for i in range(p + 1):
        col[i, p - i :] = run[p - i :] - run[p - i]
    out = np.empty((n, n), scoring.dtype)
    out[:, 0] = col[:, p]
    for c in range(q):
        sub = np.array([scoring.sub_cost(x, b[c]) for x in a], scoring.dtype)
        best = col + ins[c]
        best[:, 1:] = np.minimum(best[:, 1:], col[:, :-1] + sub)
        best[p + 1 + c, 0] = 0  # the top vertex of the new column is an input
        col = np.minimum.accumulate(best - run, axis=1) + run
        out[:, c + 1] = col[:, p]
    out[:, q:] = col[:, ::-1]
    e = excess(p, q)
    return np.where(e > 0, e * far, out)


BUILDS = {"tables": by_tables, "division": by_division, "increments": by_increments}  # by_braid: uniform costs only


def properties(d: np.ndarray) -> dict:
    """Is the matrix Monge; the most changes of difference from one column to the next."""
    second = d[1:, 1:] - d[1:, :-1] - d[:-1, 1:] + d[:-1, :-1]
    steps = np.diff(np.diff(d, axis=1), axis=0)
    return {"monge": bool((second <= 1e-9).all()), "changes": int((np.abs(steps) > 1e-9).sum(axis=0).max(initial=0))}
