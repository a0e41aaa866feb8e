"""Linear-space forms of the boundary matrix: points of its density, and permutations for gap-only scoring."""

from __future__ import annotations

import bisect
import math

import numpy as np

from . import dist as D
from . import minima


def filled(d: np.ndarray, p: int, q: int, gap) -> np.ndarray:
    """Entries without a path continue the band's edge with slope gap, so that the density stays small."""
    out = d.copy()
    n = p + q + 1
    for i in range(n):
        hi, lo = min(q + i, n - 1), max(i - p, 0)
        k = np.arange(n)
        out[i, hi + 1 :] = d[i, hi] + gap * (k[hi + 1 :] - hi)
        out[i, :lo] = d[i, lo] + gap * (lo - k[:lo])
    return out


class Points:
    """First row, first column, and the nonzero mixed second differences (row, column, amount).

    An entry is the two borders plus the amount of the points before it; a tree of sorted lists answers that in the
    square of the logarithm of their number.
    """

    def __init__(self, d: np.ndarray, p: int, q: int, gap):
        self.p, self.q, self.gap = p, q, gap
        f = filled(d, p, q, gap)
        self.top, self.left = f[0].copy(), f[:, 0].copy()
        density = f[1:, 1:] - f[1:, :-1] - f[:-1, 1:] + f[:-1, :-1]
        self.rows, self.cols = np.nonzero(density)
        self.amount = density[self.rows, self.cols]
        self.tree: list | None = None

    def __len__(self) -> int:
        return len(self.rows)

    @property
    def mass(self):
        return -self.amount.sum()

    def dense(self, far=None) -> np.ndarray:
        n = self.p + self.q + 1
        out = np.zeros((n, n), self.top.dtype)
        out[self.rows + 1, self.cols + 1] = self.amount
        out = out.cumsum(axis=0).cumsum(axis=1) + self.left[:, None] + self.top[None, :] - self.top[0]
        return out if far is None else D.outside(out, self.p, self.q, far)

    def _grow(self) -> None:
        """Levels of blocks of 2**k points in row order, each sorted by column with running amounts."""
        self.tree, width = [], 1
        order = np.argsort(self.rows, kind="stable")
        self.sorted_rows = self.rows[order].tolist()
        cols, amount = self.cols[order], self.amount[order]
        while width <= max(len(order), 1):
            level = []
            for s in range(0, len(order), width):
                at = np.argsort(cols[s : s + width], kind="stable")
                level.append((cols[s : s + width][at].tolist(), [0, *np.cumsum(amount[s : s + width][at]).tolist()]))
            self.tree.append(level)
            width *= 2

    def query(self, i: int, j: int):
        if self.tree is None:
            self._grow()
        n = bisect.bisect_left(self.sorted_rows, i)  # points in rows before i
        total, at = self.left[i].item() + self.top[j].item() - self.top[0].item(), 0
        for k in reversed(range(len(self.tree))):
            if n >> k & 1:
                cols, sums = self.tree[k][at >> k]
                total += sums[bisect.bisect_left(cols, j)]
                at += 1 << k
        return total


class Linear:
    """A boundary matrix as terms of its rows and columns and points, stored by row and by column: linear space. Entry
    (i, j) is left[i] + top[j] plus the amounts of the points in rows before i and columns before j. Entries without
    a path hold what the path along the block's edge and back would cost, never less than a real way round."""

    def __init__(self, left: np.ndarray, top: np.ndarray, row: np.ndarray, col: np.ndarray, amount: np.ndarray):
        n = len(left)
        self.left, self.top = left, top
        at = np.argsort(row, kind="stable")
        self.col, self.amount = col[at], amount[at]
        self.row_at = np.r_[0, np.cumsum(np.bincount(row, minlength=n))][:n]
        at = np.argsort(col, kind="stable")
        self.row, self.amount_by_col = row[at], amount[at]
        self.col_at = np.r_[0, np.cumsum(np.bincount(col, minlength=n))][:n]

    def __len__(self) -> int:
        return len(self.col)

    @property
    def nbytes(self) -> int:
        return 8 * (4 * len(self.left) + 4 * len(self.col))

    @staticmethod
    def of_braid(perm: np.ndarray, scoring) -> Linear:
        """From the braid of two texts blown up by copies(): one point a strand."""
        marks, letters = copies(scoring)
        nu = marks + letters
        step = scoring.dtype((scoring.delete + scoring.insert) // nu)
        n = np.arange(len(perm) // nu + 1)
        k = np.arange(len(perm))
        return Linear(scoring.delete * n, scoring.insert * n, k // nu, perm // nu, np.full(len(perm), -step))

    @staticmethod
    def of_texts(a: str, b: str, scoring) -> Linear:
        return Linear.of_braid(comb(blown(a, scoring), blown(b, scoring)), scoring)

    @staticmethod
    def of_points(t: Points) -> Linear:
        return Linear(t.left, t.top - t.top[0], t.rows, t.cols, t.amount)

    def dense(self) -> np.ndarray:
        n = len(self.left)
        out = np.zeros((n, n), np.result_type(self.left, self.amount))
        np.add.at(out, (np.repeat(np.arange(n), np.diff(np.r_[self.row_at, len(self)])) + 1, self.col + 1), self.amount)
        return out.cumsum(axis=0).cumsum(axis=1) + self.left[:, None] + self.top[None, :]


def copies(scoring) -> tuple[int, int]:
    """(marks, copies of the letter) a letter turns into, so that with uniform costs the distance is both gap costs less
    a multiple of the longest common subsequence: marks stand for what a replacement saves over two gaps, marks and
    letters for what a match saves."""
    both = scoring.delete + scoring.insert
    saved = max(both - scoring.replace, 0)
    unit = math.gcd(int(both), int(saved))
    return int(saved) // unit, int(both - saved) // unit


def braided(scoring) -> bool:
    """Do braids serve this scoring: the same whole-number costs for all letters, matches free."""
    return scoring.uniform and scoring.free_match and scoring.dtype is np.int64 and scoring.delete + scoring.insert > 0 and scoring.replace > 0


def blown(text: str, scoring) -> list[int]:
    """Code points, each after its marks; a mark is -1, which is no letter."""
    marks, letters = copies(scoring)
    return [x for c in text for x in [-1] * marks + [ord(c)] * letters]


def propagate(values: np.ndarray, points: Points, method: str = "halves", probes: list | None = None) -> np.ndarray:
    """Output values through the succinct form: entries are asked one by one.

    Entries without a path are answered by the large growing number, as in the dense form.
    """
    p, q, n = points.p, points.q, points.p + points.q + 1
    v = values.tolist()
    far = (max(map(abs, v)) + abs(points.dense().max()) + 1) if n < 3 else 1 << 40

    def at(i: int, j: int):
        e = max(j - q - i, i - p - j)
        return v[i] + (points.query(i, j) if e <= 0 else far * e)

    f = minima.Probes(at)
    rows = minima.METHODS[method](f, n, n)
    if probes is not None:
        probes.append(f.count)
    return np.array([at(i, j) for j, i in enumerate(rows)], values.dtype)


# --- gap-only scoring: the matrix is a permutation ---------------------------------------------------------------


def comb(a, b) -> np.ndarray:
    """Strands of the alignment braid of a against b: strand i in 0..m+n-1 (up the left side, then along the top)
    ends at place perm[i] (along the bottom, then up the right side). Two strands cross at most once."""
    m, n = len(a), len(b)
    across, down = list(range(m)), list(range(m, m + n))
    for i, x in enumerate(a):
        h = across[m - 1 - i]
        for j, y in enumerate(b):
            v = down[j]
            if x == y or h > v:
                down[j], h = h, v
        across[m - 1 - i] = h
    perm = np.empty(m + n, np.int64)
    for k, s in enumerate(across):
        perm[s] = n + k
    for k, s in enumerate(down):
        perm[s] = k
    return perm


def common(perm: np.ndarray, m: int, n: int, start: int = 0, end: int | None = None) -> int:
    """Longest common subsequence of all of a with b[start:end]: the window less the strands that stay inside it."""
    end = n if end is None else end
    return end - start - int((perm[m + start : m + n] < end).sum())


BASE = 32  # strands up to which the counts of both braids are added for all middle places at once


def product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The braid that does a, then b, with double crossings undone: divide by the middle places, merge with a
    staircase that separates where each half's count is the smaller one. n log n steps."""
    back = np.empty(len(b), np.int64)
    back[b] = np.arange(len(b))
    return _product(np.asarray(a, np.int64), back)


def _small_product(row_mid: np.ndarray, col_mid: np.ndarray) -> np.ndarray:
    """From counts(i, j) = points in rows from i on and columns before j: the product's are the least sums."""
    n = len(row_mid)
    k = np.arange(n)
    one, two = np.zeros((n + 1, n + 1), np.int16), np.zeros((n + 1, n + 1), np.int16)
    one[k, row_mid + 1] = 1
    two[col_mid, k + 1] = 1
    one, two = (x[::-1].cumsum(axis=0, dtype=np.int16)[::-1].cumsum(axis=1, dtype=np.int16) for x in (one, two))
    c = (one[:, :, None] + two[None, :, :]).min(axis=1)
    return np.argmax(c[:-1, 1:] - c[:-1, :-1] - c[1:, 1:] + c[1:, :-1], axis=1)


def _product(row_mid: np.ndarray, col_mid: np.ndarray) -> np.ndarray:
    n = len(row_mid)
    if n <= BASE:
        return _small_product(row_mid, col_mid)
    half = n // 2
    low_row, low_col = row_mid < half, col_mid < half
    merged, back = np.empty(n, np.int64), np.empty(n, np.int64)
    for low, shift in ((True, 0), (False, half)):
        rows, cols = np.flatnonzero(low_row == low), np.flatnonzero(low_col == low)
        part = cols[_product(row_mid[rows] - shift, col_mid[cols] - shift)]
        merged[rows], back[part] = part, rows
    # Let diff(i, k) = points of the upper half above and left of (i, k) less points of the lower half below and
    # right. It grows with k: the product has the lower half's points where diff <= 0, the upper half's where
    # diff >= 0. Walking up the rows, keep the last column of the one and the first column of the other. A column
    # (row) counts where its point lies on the side of the walk that its half calls for.
    row_col, col_row, low_row, low_col = merged.tolist(), back.tolist(), low_row.tolist(), low_col.tolist()
    minus_col = minus = plus_col = plus = 0
    for row in range(n, 0, -1):
        while plus_col < n and plus + (more := (col_row[plus_col] >= row) == low_col[plus_col]) <= 0:
            plus += more
            plus_col += 1
        row -= 1
        point, low = row_col[row], low_row[row]
        minus -= (point >= minus_col) == low
        plus -= (point >= plus_col) == low
        while minus < 0:
            minus += (col_row[minus_col] >= row) == low_col[minus_col]
            minus_col += 1
        if minus_col > plus_col:  # the two forms meet at this corner, where neither half has its point
            merged[row] = plus_col
    return merged


def stack_rows(top: np.ndarray, bottom: np.ndarray, m1: int, m2: int, n: int) -> np.ndarray:
    """Braid of a1 a2 against b from those of a1 (m1 letters) and a2 (m2 letters) against b."""
    above = np.r_[np.arange(m2), top + m2]
    below = np.r_[bottom, np.arange(m1) + m2 + n]
    return product(above, below)


def doubled(s: str) -> list[int]:
    """Each letter after a mark: then unit distance is both lengths less the longest common subsequence."""
    return [x for c in s for x in (-1, ord(c))]


def unit_from_common(m: int, n: int, lcs: int) -> int:
    return m + n - lcs


def perm_to_dist(perm: np.ndarray, m: int, n: int) -> np.ndarray:
    """Gap-only boundary matrix (no-path entries meaningless) from a braid: counts of strands by two running sums."""
    k = m + n
    hit = np.zeros((k + 1, k + 1), np.int64)
    hit[np.arange(k), perm + 1] = 1
    inside = hit[::-1].cumsum(axis=0)[::-1].cumsum(axis=1)  # strands that start at i or later and end before j
    i, j = np.arange(k + 1)[:, None], np.arange(k + 1)[None, :]
    score = j - (i - m) - inside
    r_in, c_in, r_out, c_out = np.maximum(m - i, 0), np.maximum(i - m, 0), m - np.maximum(j - n, 0), np.minimum(j, n)
    common_ = score - r_in - np.maximum(j - n, 0)
    return (r_out - r_in) + (c_out - c_in) - 2 * common_


def unit_dist(perm: np.ndarray, p: int, q: int, far) -> np.ndarray:
    """Unit boundary matrix of p against q letters from the braid of their doubled texts: every other vertex, halved."""
    return D.outside(np.ascontiguousarray(perm_to_dist(perm, 2 * p, 2 * q)[::2, ::2] // 2), p, q, far)
