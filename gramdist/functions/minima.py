"""Column minima of matrices whose leftmost minima move down from column to column (totally monotone ones)."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


class Probes:
    """A matrix read through a function, with a count of the entries read."""

    def __init__(self, at: Callable[[int, int], float]):
        self.at, self.count = at, 0

    def __call__(self, i: int, j: int):
        self.count += 1
        return self.at(i, j)


def naive(f, rows: int, cols: int) -> list[int]:
    """First row of each column's minimum, by reading everything."""
    return [min(range(rows), key=lambda i: (f(i, j), i)) for j in range(cols)]


def by_halves(f, rows: int, cols: int) -> list[int]:
    """The middle column splits the rows for the columns left and right of it: rows + cols probes a level."""
    out = [0] * cols
    todo = [(0, cols - 1, 0, rows - 1)]
    while todo:
        left, right, lo, hi = todo.pop()
        if left > right:
            continue
        mid = (left + right) // 2
        best, at = None, lo
        for i in range(lo, hi + 1):
            v = f(i, mid)
            if best is None or v < best:
                best, at = v, i
        out[mid] = at
        todo += [(left, mid - 1, lo, at), (mid + 1, right, at, hi)]
    return out


def by_elimination(f, rows: int, cols: int) -> list[int]:
    """Discard rows that hold no minimum until as many rows as columns are left, solve every other column, fill in."""
    out = [0] * cols

    def solve(rs: list[int], cs: list[int]) -> None:
        if not cs:
            return
        kept: list[int] = []
        for r in rs:
            while kept and f(kept[-1], cs[len(kept) - 1]) > f(r, cs[len(kept) - 1]):
                kept.pop()
            if len(kept) < len(cs):
                kept.append(r)
        solve(kept, cs[1::2])
        place = {r: k for k, r in enumerate(kept)}
        lo = 0
        for k in range(0, len(cs), 2):
            hi = place[out[cs[k + 1]]] if k + 1 < len(cs) else len(kept) - 1
            best, at = None, lo
            for i in range(lo, hi + 1):
                v = f(kept[i], cs[k])
                if best is None or v < best:
                    best, at = v, i
            out[cs[k]] = kept[at]
            lo = hi

    solve(list(range(rows)), list(range(cols)))
    return out


def spans(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, ... (size[0] of them), start[1], ..."""
    return np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size - start, size)


METHODS = {"naive": naive, "halves": by_halves, "elimination": by_elimination}


def column_minima(values: np.ndarray, dist: np.ndarray, method: str = "dense", probes: list | None = None) -> np.ndarray:
    """min over i of values[i] + dist[i, j], by the method: dense reads all entries at once."""
    if method == "dense":
        if probes is not None:
            probes.append(dist.size)
        return (values[:, None] + dist).min(axis=0)
    if method == "vector":
        return halves_at_once(values, dist, probes)
    v, d = values.tolist(), dist.tolist()
    f = Probes(lambda i, j: v[i] + d[i][j])
    rows = METHODS[method](f, *dist.shape)
    if probes is not None:
        probes.append(f.count)
    return values[rows] + dist[rows, np.arange(dist.shape[1])]


def halves_at_once(values: np.ndarray, dist: np.ndarray, probes: list | None = None) -> np.ndarray:
    """by_halves with all columns of a level in one vector: rows + columns reads a level, no Python loop over them."""
    rows, cols = dist.shape
    arg = np.zeros(cols, np.int64)
    low = np.empty(cols, values.dtype)
    step = 1 << max(0, (cols - 1).bit_length())
    known = np.zeros(0, np.int64)
    read = 0
    while step:
        at = np.arange(step - 1, cols, 2 * step)
        if len(at):
            lo = np.where(at - step >= 0, arg[np.maximum(at - step, 0)], 0) if len(known) else np.zeros(len(at), np.int64)
            hi = np.where(at + step < cols, arg[np.minimum(at + step, cols - 1)], rows - 1) if len(known) else np.full(len(at), rows - 1)
            hi = np.maximum(lo, hi)  # rounding may swap ties of floats
            size = hi - lo + 1
            cut = np.r_[0, np.cumsum(size)[:-1]]
            col = np.repeat(at, size)
            row = np.arange(len(col)) - np.repeat(cut - lo, size)
            v = values[row] + dist[row, col]
            best = np.minimum.reduceat(v, cut)
            first = np.flatnonzero(v == np.repeat(best, size))
            where = first[np.searchsorted(first, cut)]
            arg[at], low[at] = row[where], best
            read += len(col)
            known = at
        step //= 2
    if probes is not None:
        probes.append(read)
    return low


def halves_of_many(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """min over k of x[t, i, k] + y[t, k, j] for every t, each row searched as by halves_at_once, and reads by t."""
    (t, n, m), w = x.shape, y.shape[2]
    lanes = t * n
    low, arg = np.empty((lanes, w), np.result_type(x, y)), np.empty((lanes, w), np.int32)
    x, y = np.ascontiguousarray(x).reshape(-1), np.ascontiguousarray(y).reshape(-1)
    read = np.zeros(lanes, np.int64)
    own, table = np.arange(lanes, dtype=np.int64)[:, None] * m, np.repeat(np.arange(t, dtype=np.int64) * m * w, n)[:, None]
    step = 1 << (w - 1).bit_length()
    while step:
        at = np.arange(step - 1, w, 2 * step)
        if len(at):
            lo, hi = np.zeros((lanes, len(at)), np.int64), np.full((lanes, len(at)), m - 1, np.int64)
            left, right = at >= step, at + step < w
            lo[:, left], hi[:, right] = arg[:, at[left] - step], arg[:, at[right] + step]
            hi = np.maximum(lo, hi)  # rounding may swap ties of floats
            size = hi - lo + 1
            read += size.sum(axis=1)
            best, where = x[own + lo] + y[table + lo * w + at], lo.copy()
            wide = np.flatnonzero(size > 1)
            if len(wide):
                more = size.reshape(-1)[wide] - 1
                k = spans(lo.reshape(-1)[wide] + 1, more)
                cell = np.repeat(wide, more)
                lane, col = np.divmod(cell, len(at))
                v = x[lane * m + k] + y[table[lane, 0] + k * w + at[col]]
                cut = np.cumsum(more) - more
                least = np.minimum.reduceat(v, cut)
                hit = np.flatnonzero(v == np.repeat(least, more))
                first = k[hit[np.searchsorted(hit, cut)]]
                less = least < best.reshape(-1)[wide]
                best.reshape(-1)[wide[less]], where.reshape(-1)[wide[less]] = least[less], first[less]
            low[:, at], arg[:, at] = best, where
        step //= 2
    return low.reshape(t, n, w), read.reshape(t, n).sum(axis=1)


def dense_minima(values: list[np.ndarray], at_pool: np.ndarray, pool: np.ndarray, probes: list | None = None) -> list[np.ndarray]:
    """by_halves for several blocks at once over dense tables that lie in one flat pool, each from its place on."""
    n = np.array([len(v) for v in values])
    first = np.cumsum(n) - n
    base = np.concatenate(values)
    arg, low = np.zeros(len(base), np.int64), np.empty(len(base), np.result_type(base, pool))
    step, read = 1 << int(n.max() - 1).bit_length(), 0
    while step:
        many = np.maximum(0, -(-(n - (step - 1)) // (2 * step)))
        at = np.repeat(first + step - 1, many) + 2 * step * spans(np.zeros(len(n), np.int64), many)
        if len(at):
            top, side = np.repeat(first, many), np.repeat(n, many)
            end, left, right = top + side, at - step, at + step
            lo = np.where(left >= top, arg[np.maximum(left, top)], top)
            hi = np.where(right < end, arg[np.minimum(right, end - 1)], end - 1)
            lo, hi = np.minimum(lo, hi), np.maximum(lo, hi)
            rows = hi - lo + 1
            row = spans(lo, rows)
            v = base[row] + pool[np.repeat(np.repeat(at_pool, many) + at - top - top * side, rows) + row * np.repeat(side, rows)]
            cut = np.cumsum(rows) - rows
            best = np.minimum.reduceat(v, cut)
            hit = np.flatnonzero(v == np.repeat(best, rows))
            arg[at], low[at] = row[hit[np.searchsorted(hit, cut)]], best
            read += len(v)
        step //= 2
    if probes is not None:
        probes.append(read)
    return np.split(low, first[1:])


def linear_minima(values: list[np.ndarray], tables: list, probes: list | None = None) -> list[np.ndarray]:
    """by_halves for several blocks at once over their linear-space tables (succinct.Linear), never expanded.

    An entry is a term of its row, one of its column and the amounts of the points above and left of it. Within a
    level the sum moves down a column by the points of one row a step, and from a known column to the next one by the
    points of the columns between, so a level reads rows plus columns and as many points.
    """
    n = np.array([len(v) for v in values])
    first = np.cumsum(n) - n
    shift = np.cumsum([len(t.col) for t in tables]) - [len(t.col) for t in tables]
    join = np.concatenate
    base = join([v + t.left for v, t in zip(values, tables)])
    ptr, cptr = (join([getattr(t, k) + s for t, s in zip(tables, shift)]) for k in ("row_at", "col_at"))
    col, row_of = (join([getattr(t, k) + f for t, f in zip(tables, first)]) for k in ("col", "row"))
    by_row, by_col = (join([getattr(t, k) for t in tables]) for k in ("amount", "amount_by_col"))
    total = len(base)
    arg, count, low = np.zeros(total, np.int64), np.zeros(total, by_row.dtype), np.empty(total, base.dtype)
    step, read = 1 << int(n.max() - 1).bit_length(), 0
    while step:
        many = np.maximum(0, -(-(n - (step - 1)) // (2 * step)))
        at = np.repeat(first + step - 1, many) + 2 * step * spans(np.zeros(len(n), np.int64), many)
        if len(at):
            top, end = np.repeat(first, many), np.repeat(first + n, many)
            left, right = at - step, at + step
            known = left >= top
            left = np.where(known, left, top)
            lo = np.where(known, arg[left], top)
            hi = np.maximum(lo, np.where(right < end, arg[np.minimum(right, end - 1)], end - 1))  # rounding may swap ties
            # the sum at (lo, at), from that at (lo, left)
            a = cptr[left]
            size = cptr[at] - a
            i = spans(a, size)
            run = np.r_[0, np.cumsum(np.where(row_of[i] < np.repeat(lo, size), by_col[i], 0))]
            cut = np.cumsum(size)
            start = np.where(known, count[left], 0) + run[cut] - run[cut - size]
            # and at all rows from lo to hi
            a = ptr[lo]
            size = ptr[hi] - a
            i = spans(a, size)
            run = np.r_[0, np.cumsum(np.where(col[i] < np.repeat(at, size), by_row[i], 0))]
            off = np.cumsum(size) - size
            rows = hi - lo + 1
            row = spans(lo, rows)
            sums = run[ptr[row] + np.repeat(off - a, rows)] + np.repeat(start - run[off], rows)
            v = base[row] + sums
            cut = np.cumsum(rows) - rows
            best = np.minimum.reduceat(v, cut)
            hit = np.flatnonzero(v == np.repeat(best, rows))
            where = hit[np.searchsorted(hit, cut)]
            arg[at], count[at], low[at] = row[where], sums[where], best
            read += len(v)
        step //= 2
    if probes is not None:
        probes.append(read)
    low += join([t.top for t in tables])
    return np.split(low, first[1:])


def monge_product(x: np.ndarray, y: np.ndarray, probes: list | None = None, at_once: int = 1 << 20) -> np.ndarray:
    """min over k of x[i, k] + y[k, j] of two Monge matrices. The least k never falls from one row or column to the
    next, so it is found on a grid whose spacing is halved again and again: all rows for the new columns, then all
    columns for the new rows. A level reads its grid lines times (rows + inner side), and the sum is quadratic."""
    (n, m), w = x.shape, y.shape[1]
    out, arg = np.empty((n, w), np.result_type(x, y)), np.zeros((n, w), np.int64)
    read = 0

    def fill(r: np.ndarray, c: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> int:
        size = hi - lo + 1
        cut = np.r_[0, np.cumsum(size)]
        s = 0
        while s < len(r):
            e = max(s + 1, int(np.searchsorted(cut, cut[s] + at_once, "right")) - 1)
            own = size[s:e]
            k = spans(lo[s:e], own)
            v = x[np.repeat(r[s:e], own), k] + y[k, np.repeat(c[s:e], own)]
            at = cut[s:e] - cut[s]
            best = np.minimum.reduceat(v, at)
            hit = np.flatnonzero(v == np.repeat(best, own))
            out[r[s:e], c[s:e]] = best
            arg[r[s:e], c[s:e]] = k[hit[np.searchsorted(hit, at)]]
            s = e
        return int(cut[-1])

    step = 1 << (max(n, w) - 1).bit_length()
    while step:
        for new in (True, False):  # new columns on known rows, then new rows on all columns
            rows = np.arange(2 * step - 1, n, 2 * step) if new else np.arange(step - 1, n, 2 * step)
            cols = np.arange(step - 1, w, 2 * step) if new else np.arange(step - 1, w, step)
            if not len(rows) or not len(cols):
                continue
            r, c = np.repeat(rows, len(cols)), np.tile(cols, len(rows))
            before, after = (c - step, c + step) if new else (r - step, r + step)
            end = w if new else n
            b, a = np.maximum(before, 0), np.minimum(after, end - 1)
            lo = np.where(before >= 0, arg[r, b] if new else arg[b, c], 0)
            hi = np.where(after < end, arg[r, a] if new else arg[a, c], m - 1)
            read += fill(r, c, np.minimum(lo, hi), np.maximum(lo, hi))  # rounding may swap ties of floats
        step //= 2
    if probes is not None:
        probes.append(read)
    return out
