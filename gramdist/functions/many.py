"""The block method on many pairs at once, for blocks of few inputs: boundary matrices of one shape are merged together,
and blocks of one shape on a falling diagonal are swept together, whatever pair they belong to.

Tables are found by the texts of both symbols, so equal segments share one among all pairs of a batch. The tables of a
shape are one array whose last axis is the table, so that numpy's inner loops run over many tables and not over the few
inputs of one.
"""

from __future__ import annotations

from collections import Counter

import numpy as np

from ..scoring import Scoring
from . import cuts, minima
from . import dist as D
from . import succinct as S

BYTES = 1 << 27  # of a batch's tables; more of them halve the batch
BLOCKS = 1 << 20  # blocks of a batch
PAIRS = 1024
AT_ONCE = 1 << 18  # bytes of sums that a merge or a sweep holds at once
LANES = 64  # tables that are merged at once, however large
WIDE = 160  # inputs of a block up to which its matrix is merged with others
STRANDS = 64  # of a braid up to which it is merged with others


class Symbols:
    """Different texts with the two they are split into where they first occur."""

    def __init__(self):
        self.of: dict[str, int] = {}
        self.text: list[str] = []
        self.lhs: list[int] = []
        self.rhs: list[int] = []
        self.size: list[int] = []
        self.letter: list[str] = []

    def add(self, c: cuts.Cut) -> np.ndarray:
        """Numbers of a cut's segments."""
        need, todo = set(), list(dict.fromkeys(c.segments))
        while todo:
            v = todo.pop()
            if v not in need:
                need.add(v)
                if c.lhs[v] >= 0:
                    todo += [c.lhs[v], c.rhs[v]]
        text: dict[int, str] = {}
        to: dict[int, int] = {}
        for v in sorted(need):  # children come before
            l, r = c.lhs[v], c.rhs[v]
            t = text[v] = chr(r) if l < 0 else text[l] + text[r]
            k = self.of.get(t)
            if k is None:
                k = self.of[t] = len(self.lhs)
                self.lhs.append(-1 if l < 0 else to[l])
                self.rhs.append(-1 if l < 0 else to[r])
                self.size.append(len(t))
                self.letter.append(t if l < 0 else "")
                self.text.append(t)
            to[v] = k
        return np.array([to[v] for v in c.segments], np.int64)


def _runs(*keys: np.ndarray) -> list[tuple[int, int]]:
    """(start, end) of the equal stretches of sorted keys."""
    n = len(keys[0])
    new = np.zeros(n + 1, bool)
    new[[0, n]] = True
    for k in keys:
        new[1:n] |= k[1:] != k[:-1]
    at = np.flatnonzero(new).tolist()
    return list(zip(at, at[1:])) if n else []


def _spread(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start, start + 1, ... count times, one after another."""
    total = int(count.sum())
    return np.arange(total) + np.repeat(start - (np.cumsum(count) - count), count)


class Dense:
    """Tables of one shape as they are."""

    def __init__(self, tables: np.ndarray):
        self.tables = tables

    def dense(self, rows: np.ndarray) -> np.ndarray:
        return np.take(self.tables, rows, axis=2)


class Density:
    """Tables of one shape as their first rows and columns and density points (see succinct.Points)."""

    def __init__(self, d: np.ndarray, p: int, q: int, gap, far: np.ndarray):
        d, n = np.moveaxis(d, 2, 0), p + q + 1
        k = np.arange(n)
        at = np.clip(k[None, :], np.maximum(k - p, 0)[:, None], np.minimum(k + q, n - 1)[:, None])
        f = d[:, k[:, None], at] + (gap * np.abs(at - k)).astype(d.dtype)
        self.far, self.top, self.left = far, f[:, 0, :].copy(), f[:, :, 0].copy()
        density = f[:, 1:, 1:] - f[:, 1:, :-1] - f[:, :-1, 1:] + f[:, :-1, :-1]
        which, self.row, self.col = np.nonzero(density)
        self.amount = density[which, self.row, self.col]
        self.count = np.bincount(which, minlength=len(d))
        self.start = np.cumsum(self.count) - self.count

    def dense(self, rows: np.ndarray) -> np.ndarray:
        top, left, count = self.top[rows], self.left[rows], self.count[rows]
        n = top.shape[1]
        out = np.zeros((len(rows), n, n), top.dtype)
        k = _spread(self.start[rows], count)
        out[np.repeat(np.arange(len(rows)), count), self.row[k] + 1, self.col[k] + 1] = self.amount[k]
        out = out.cumsum(axis=1, dtype=out.dtype).cumsum(axis=2, dtype=out.dtype)
        out += left[:, :, None]
        out += (top - top[:, :1])[:, None, :]
        np.copyto(out, self.far, where=self.far > 0)
        return np.ascontiguousarray(np.moveaxis(out, 0, 2))


class Braids:
    """Tables of one shape as braids, a row of strands each."""

    def __init__(self, strands: np.ndarray, scoring: Scoring, far: np.ndarray):
        self.strands, self.s, self.far = strands, scoring, far

    def dense(self, rows: np.ndarray) -> np.ndarray:
        nu, n = sum(S.copies(self.s)), len(self.far)
        step = (self.s.delete + self.s.insert) // nu
        perm = self.strands[rows].astype(np.int64)
        at = (np.arange(len(rows))[:, None] * n + np.arange(perm.shape[1]) // nu + 1) * n + perm // nu + 1
        hit = np.bincount(at.reshape(-1), minlength=len(rows) * n * n).reshape(-1, n, n)
        out = -step * hit.cumsum(axis=1).cumsum(axis=2)
        k = np.arange(n)
        out += self.s.delete * k[:, None] + self.s.insert * k
        out = out.astype(self.far.dtype)
        np.copyto(out, self.far, where=self.far > 0)
        return np.ascontiguousarray(np.moveaxis(out, 0, 2))


def combs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """succinct.comb of many pairs of texts as rows of codes, all of one length each."""
    m, n = a.shape[1], b.shape[1]
    across, down = [np.full(len(a), k, np.int16) for k in range(m)], [np.full(len(a), m + k, np.int16) for k in range(n)]
    for i in range(m):
        h = across[m - 1 - i]
        for j in range(n):
            v = down[j]
            swap = (a[:, i] == b[:, j]) | (h > v)
            down[j], h = np.where(swap, h, v), np.where(swap, v, h)
        across[m - 1 - i] = h
    perm, lane = np.empty((len(a), m + n), np.int16), np.arange(len(a))
    for k, s in enumerate(across):
        perm[lane, s] = n + k
    for k, s in enumerate(down):
        perm[lane, s] = k
    return perm


def products(top: np.ndarray, bottom: np.ndarray, m1: int, m2: int, n: int, lanes: int = 256) -> np.ndarray:
    """succinct.stack_rows of many braids by least sums of counts over all middle places."""
    k = m1 + m2 + n
    out = np.empty((len(top), k), np.int16)
    place = np.arange(k)
    for s in range(0, len(top), lanes):
        e = min(s + lanes, len(top))
        lane = np.arange(e - s)
        one, two = np.zeros((k + 1, k + 1, e - s), np.uint8), np.zeros((k + 1, k + 1, e - s), np.uint8)
        one[place[:m2], place[:m2] + 1] = 1
        one[place[m2:, None], top[s:e].T + m2 + 1, lane] = 1
        two[place[: m2 + n, None], bottom[s:e].T + 1, lane] = 1
        two[place[m2 + n :], place[m2 + n :] + 1] = 1
        for x in (one, two):  # points in rows from i on and columns before j
            for i in range(k - 1, -1, -1):
                x[i] += x[i + 1]
            for j in range(k):
                x[:, j + 1] += x[:, j]
        c = one[:, 0][:, None] + two[0]
        spare = np.empty_like(c)
        for mid in range(1, k + 1):
            np.add(one[:, mid][:, None], two[mid], out=spare)
            np.minimum(c, spare, out=c)
        hit = c[:-1, 1:] + c[1:, :-1] != c[:-1, :-1] + c[1:, 1:]
        out[s:e] = np.argmax(hit, axis=1).T
    return out


class Batch:
    """Boundary matrices and sweep of many pairs of cuts. form: dense, points or perm, as those of blocks.Repository;
    strips are dense tables of which only the first text is split. merge: monge (reads all) or vector."""

    def __init__(self, pairs: list[tuple[cuts.Cut, cuts.Cut]], scoring: Scoring, recursion: str = "one_sided", form: str = "dense", merge: str = "monge"):
        self.s, self.recursion, self.form, self.merge = scoring, recursion, form, merge
        sym = Symbols()
        self.segments = [(sym.add(a), sym.add(b)) for a, b in pairs]
        self.lhs, self.rhs, self.size = (np.array(x, np.int64) for x in (sym.lhs, sym.rhs, sym.size))
        self.letter, self.text = sym.letter, sym.text
        self.count = [Counter(distinct=len(set(a.segments)) * len(set(b.segments))) for a, b in pairs]
        whole = np.issubdtype(scoring.dtype, np.integer)
        reach = 4 * int(self.size.max()) * (int(scoring.largest) + 1) if whole else 0
        small = whole and reach < 1 << 13 and merge != "vector"  # a search needs numbers that grow outside the band
        self.dtype = np.dtype(np.int16 if small else scoring.dtype)
        self.far = self.dtype.type(1 << 13) if small else D.big(scoring)
        if small and form == "dense" and 2 * int(self.size.max()) * int(scoring.largest) < 127:  # no path costs as much
            self.dtype, self.far = np.dtype(np.uint8), np.uint8(127)
        self._keys()

    def _keys(self) -> None:
        """All pairs of symbols whose table is needed: those of segments, then what each is merged from."""
        m = len(self.lhs)
        keys, owner = [], []
        for k, (a, b) in enumerate(self.segments):
            own = (np.unique(a)[:, None] * m + np.unique(b)).reshape(-1)
            keys.append(own)
            owner.append(np.full(len(own), k))
        new, at = np.unique(np.concatenate(keys), return_index=True)
        who = np.concatenate(owner)[at]
        every, owners = new, who
        while len(new):
            kids, of = [], []
            for rows, parts in self._children(new // m, new % m):
                for u, v in parts:
                    kids.append(u * m + v)
                    of.append(who[rows])
            if not kids:
                break
            new, at = np.unique(np.concatenate(kids), return_index=True)
            who = np.concatenate(of)[at]
            there = every[np.minimum(np.searchsorted(every, new), len(every) - 1)] == new
            new, who = new[~there], who[~there]
            order = np.argsort(np.concatenate([every, new]), kind="stable")
            every, owners = np.concatenate([every, new])[order], np.concatenate([owners, who])[order]
        self.m, self.keys = m, every
        self.u, self.v = every // m, every % m
        self.p, self.q = self.size[self.u], self.size[self.v]
        self.owners = owners
        self.bytes = int(((self.p + self.q + 1) ** 2).sum()) * self.dtype.itemsize

    def _children(self, u: np.ndarray, v: np.ndarray):
        """(rows, pairs of symbols that their tables are merged from), by kind: above each other, side by side, both."""
        p, q = self.size[u], self.size[v]
        if self.form in ("perm", "strips"):
            down = np.flatnonzero(p > 1)
            yield down, [(self.lhs[u[down]], v[down]), (self.rhs[u[down]], v[down])]
            return
        four = (p > 1) & (q > 1) if self.recursion == "four_way" else np.zeros(len(p), bool)
        down = np.flatnonzero((p >= q) & (p > 1) & ~four)
        side = np.flatnonzero((p < q) & ~four)
        four = np.flatnonzero(four)
        l, r = self.lhs, self.rhs
        yield down, [(l[u[down]], v[down]), (r[u[down]], v[down])]
        yield side, [(u[side], l[v[side]]), (u[side], r[v[side]])]
        yield four, [(x[u[four]], y[v[four]]) for x in (l, r) for y in (l, r)]

    def _find(self, u, v) -> np.ndarray:
        return np.searchsorted(self.keys, u * self.m + v)

    def build(self) -> None:
        """Every table, those of few letters first; a shape's tables are one array."""
        p, q = self.p, self.q
        kind = np.zeros(len(p), np.int64)
        parts = np.zeros((len(p), 4), np.int64)
        for k, (rows, kids) in enumerate(self._children(self.u, self.v), 1):
            kind[rows] = k
            for n, (u, v) in enumerate(kids):
                parts[rows, n] = self._find(u, v)
        p1, q1 = p[parts[:, 0]], q[parts[:, 0]]
        order = np.lexsort((q1, p1, kind, q, p, p + q))
        self.place = np.empty(len(p), np.int64)
        self.pool: dict = {}
        merges, probes, points = (np.zeros(len(p), np.int64) for _ in range(3))
        for lo, hi in _runs(p[order], q[order]):
            rows = order[lo:hi]
            h, w = int(p[rows[0]]), int(q[rows[0]])
            self.place[rows] = np.arange(len(rows))
            far = self._outside(h, w)
            out = far > 0
            if self.form == "perm":
                strands, points[rows] = self._braids(rows, kind, parts, h, w), sum(S.copies(self.s)) * (h + w)
                merges[rows] = kind[rows]
                self.pool[h, w] = Braids(strands, self.s, far)
                continue
            own = np.empty((h + w + 1, h + w + 1, len(rows)), self.dtype)
            for a, b in _runs(kind[rows], p1[rows], q1[rows]):
                some, k = rows[a:b], int(kind[rows[a]])
                if k == 0:
                    own[:, :, a:b] = np.moveaxis(self._leaves(some) if self.form != "strips" else self._strips(some, w), 0, 2)
                    continue
                d = [self.pool[int(p[x[0]]), int(q[x[0]])].dense(self.place[x]) for x in parts[some, : 4 if k == 3 else 2].T]
                ph, qw = int(p1[some[0]]), int(q1[some[0]])
                merges[some] = 3 if k == 3 else 1
                if k == 1:
                    probes[some] = self._rows(own[:, :, a:b], *d, ph, h - ph, w)
                elif k == 2:
                    probes[some] = self._columns(own[:, :, a:b], *d, h, qw, w - qw)
                else:
                    top, low = (np.empty((t + w + 1, t + w + 1, len(some)), self.dtype) for t in (ph, h - ph))
                    n = self._columns(top, d[0], d[1], ph, qw, w - qw) + self._columns(low, d[2], d[3], h - ph, qw, w - qw)
                    for x, t in ((top, ph), (low, h - ph)):
                        np.copyto(x, self._outside(t, w)[:, :, None], where=(D.excess(t, w) > 0)[:, :, None])
                    probes[some] = n + self._rows(own[:, :, a:b], top, low, ph, h - ph, w)
            np.copyto(own, far[:, :, None], where=out[:, :, None])
            self.pool[h, w] = Dense(own)
            if self.form == "points":
                self.pool[h, w] = Density(own, h, w, self.s.delete, far)
                points[rows] = self.pool[h, w].count
        held = ("entries", (p + q + 1) ** 2) if self.form in ("dense", "strips") else ("points", points)
        for name, n in (("tables", np.ones(len(p), np.int64)), held, ("merges", merges), ("leaves", kind == 0), ("merge_probes", probes)):
            for k, x in enumerate(np.bincount(self.owners, n, len(self.count)).astype(np.int64).tolist()):
                if x:
                    self.count[k][name] += x

    def _outside(self, p: int, q: int) -> np.ndarray:
        """What stands where no path leads, 0 elsewhere."""
        e = D.excess(p, q)
        return (e if self.merge == "vector" else e > 0).astype(self.dtype) * self.far

    def _braids(self, rows: np.ndarray, kind: np.ndarray, parts: np.ndarray, h: int, w: int) -> np.ndarray:
        """The braids of some symbols of h letters and others of w: combed for single letters, else merged."""
        nu = sum(S.copies(self.s))
        strands = np.empty((len(rows), nu * (h + w)), np.int16)
        for a, b in _runs(kind[rows], self.p[parts[rows, 0]]):
            some = rows[a:b]
            if not kind[some[0]]:
                code = [np.array([S.blown(self.text[v], self.s) for v in x[some].tolist()], np.int32) for x in (self.u, self.v)]
                strands[a:b] = combs(*code)
                continue
            m1 = int(self.p[parts[some[0], 0]])
            d = [self.pool[m, w].strands[self.place[x]] for m, x in zip((m1, h - m1), parts[some, :2].T)]
            strands[a:b] = products(*d, nu * m1, nu * (h - m1), nu * w)
        return strands

    def _strips(self, rows: np.ndarray, q: int) -> np.ndarray:
        """As dist.by_increments, of single letters against texts of q."""
        s, n = self.s, q + 2
        x, y = ([t[v] for v in c[rows].tolist()] for t, c in ((self.letter, self.u), (self.text, self.v)))
        dele = np.array([s.del_cost(c) for c in x], self.dtype)[:, None]
        ins, sub = (np.empty((len(rows), q), self.dtype) for _ in range(2))
        for k, (c, t) in enumerate(zip(x, y)):
            ins[k], sub[k] = [s.ins_cost(z) for z in t], [s.sub_cost(c, z) for z in t]
        above, below = np.full((len(rows), n), 2 * self.far, self.dtype), np.full((len(rows), n), 2 * self.far, self.dtype)
        below[:, 0], above[:, 1], below[:, 1:2] = 0, 0, dele
        out = np.empty((len(rows), n, n), self.dtype)
        out[:, :, 0] = below
        for k in range(q):
            low = np.minimum(below + ins[:, k : k + 1], above + sub[:, k : k + 1])
            above = np.minimum(above + ins[:, k : k + 1], 2 * self.far)
            above[:, k + 2] = 0
            below = np.minimum(np.minimum(low, above + dele), 2 * self.far)
            out[:, :, k + 1] = below
        out[:, :, q + 1] = above
        return out

    def _leaves(self, rows: np.ndarray) -> np.ndarray:
        out = np.empty((len(rows), 3, 3), self.dtype)
        for k, (u, v) in enumerate(zip(self.u[rows].tolist(), self.v[rows].tolist())):
            x, y = self.letter[u], self.letter[v]
            d, i = self.s.del_cost(x), self.s.ins_cost(y)
            out[k] = [[0, i, self.far], [d, min(self.s.sub_cost(x, y), d + i), i], [self.far, d, 0]]
        return out

    def _rows(self, out, d1, d2, p1: int, p2: int, q: int):
        """As dist.merge_rows, of many."""
        probes = self._cross(out[p2:, : q + p2 + 1], d1[:, : q + 1], d2[p2:])
        out[p2:, q + p2 :] = d1[:, q:]
        out[: p2 + 1, : q + p2 + 1] = d2[: p2 + 1]
        return probes

    def _columns(self, out, d1, d2, p: int, q1: int, q2: int):
        probes = self._cross(out[: p + q1 + 1, q1:], d1[:, q1:], d2[: p + 1])
        out[: p + q1 + 1, : q1 + 1] = d1[:, : q1 + 1]
        out[p + q1 :, q1:] = d2[p:]
        return probes

    def _cross(self, out: np.ndarray, x: np.ndarray, y: np.ndarray):
        """The least sums of many, and how many were read: for all tables alike, or for each."""
        if self.merge == "vector":
            best, read = minima.halves_of_many(np.moveaxis(x, 2, 0), np.moveaxis(y, 2, 0))
            out[:] = np.moveaxis(best, 0, 2)
            return read
        n, m, w = len(x), len(y), y.shape[1]
        if out.shape[2] < w:  # few tables of a large shape: along their rows
            u, v = (np.ascontiguousarray(np.moveaxis(z, 2, 0)) for z in (x, y))
            best = u[:, :, :1] + v[:, :1]
            spare = np.empty_like(best)
            for k in range(1, m):
                np.add(u[:, :, k : k + 1], v[:, k : k + 1], out=spare)
                np.minimum(best, spare, out=best)
            out[:] = np.moveaxis(best, 0, 2)
            return n * m * w
        lanes = max(LANES, AT_ONCE // (n * w * out.itemsize))
        spare = np.empty((n, w, min(lanes, out.shape[2])), out.dtype)
        for s in range(0, out.shape[2], lanes):
            own = slice(s, s + lanes)
            u, v = np.ascontiguousarray(x[:, :, own]), np.ascontiguousarray(y[:, :, own])
            best = u[:, 0, None] + v[0]
            some = spare[:, :, : best.shape[2]]
            for k in range(1, m):
                np.add(u[:, k, None], v[k], out=some)
                np.minimum(best, some, out=best)
            out[:, :, own] = best
        return n * m * w

    def sweep(self, borders: bool = False, most: int = 1 << 30) -> list:
        """The distance of each pair, in numerators; borders also keeps what is below every row of blocks: for each pair
        an array of a row for each segment of a and a column for each place of b, 0 included. Blocks of more than most
        inputs are searched, others read whole."""
        s, size = self.s, self.size
        tops, lefts = [], []
        cost = {x: (s.dtype(s.del_cost(x)), s.dtype(s.ins_cost(x))) for x in {t for t in self.letter if t}}
        texts = np.cumsum(size) - size
        order = np.frombuffer("".join(self.text).encode("utf-32-le"), np.uint32)
        code, which = np.unique(order, return_inverse=True)
        dele, ins = (np.array([cost[chr(c)][k] for c in code.tolist()], s.dtype)[which] for k in (0, 1))
        top_at, left_at, t_sum, l_sum = [], [], 0, 0
        for a, b in self.segments:
            for segs, gaps, out, at, total, flip in ((b, ins, tops, top_at, t_sum, False), (a, dele, lefts, left_at, l_sum, True)):
                n = size[segs]
                first = np.cumsum(n) - n
                at.append(total + first + np.arange(len(n)))
                run = np.concatenate([np.zeros(1, s.dtype), np.cumsum(gaps[_spread(texts[segs], n)])])
                places = _spread(first, n + 1)
                out.append(run[np.repeat(2 * first + n, n + 1) - places if flip else places])
                total += len(places)
                if flip:
                    l_sum = total
                else:
                    t_sum = total
        tops, lefts = np.concatenate(tops), np.concatenate(lefts)
        last = [int(t[-1] + size[b[-1]]) for t, (_, b) in zip(top_at, self.segments)]
        high, wide = (np.array([len(x[k]) for x in self.segments]) for k in (0, 1))
        blocks = high * wide
        pair = np.repeat(np.arange(len(blocks), dtype=np.int32), blocks)
        within = _spread(np.zeros(len(blocks), np.int64), blocks)
        row, col = np.divmod(within, wide[pair])
        a_at, b_at = row + (np.cumsum(high) - high)[pair], col + (np.cumsum(wide) - wide)[pair]
        us, vs = (np.concatenate([x[k] for x in self.segments])[at] for k, at in ((0, a_at), (1, b_at)))
        lo_at, to_at = np.concatenate(left_at)[a_at], np.concatenate(top_at)[b_at]
        p, q = size[us], size[vs]
        place = self.place[self._find(us, vs)]
        if borders:
            width = [int(size[b].sum()) + 1 for _, b in self.segments]
            base = np.cumsum([0, *[len(a) * w for (a, _), w in zip(self.segments, width)]])
            kept = np.empty(int(base[-1]), s.dtype)
            b_at = np.concatenate([np.add.outer(np.arange(len(a)) * w, np.cumsum(size[b]) - size[b]).reshape(-1) for (a, b), w in zip(self.segments, width)]) + base[pair]
        probes = np.where(p + q < most, (p + q + 1) ** 2, 0)
        shape, kinds = p * (int(q.max()) + 1) + q, {}
        names, shape = np.unique(shape, return_inverse=True)
        for k, v in enumerate(names.tolist()):
            h, w = divmod(v, int(q.max()) + 1)
            x = self.pool[h, w]
            if isinstance(x, Dense):
                kinds[k] = x.tables
            else:
                used = np.flatnonzero(shape == k)
                here, place[used] = np.unique(place[used], return_inverse=True)
                kinds[k] = x.dense(here)
        t = (row + col) * len(names) + shape
        order = np.argsort(t.astype(np.uint16) if int(t.max()) < 1 << 16 else t, kind="stable")
        for lo, hi in _runs(t[order]):
            every = order[lo:hi]
            h, w, table = int(p[every[0]]), int(q[every[0]]), kinds[int(shape[every[0]])]
            step = max(16, AT_ONCE // (table.itemsize * (h + w + 1) ** 2))
            for some in (every[k : k + step] for k in range(0, len(every), step)):
                at_l, at_t = lo_at[some] + np.arange(h + 1)[:, None], to_at[some] + np.arange(w + 1)[:, None]
                into = np.concatenate([lefts[at_l], tops[at_t[1:]]])
                corner = into[h]
                own = np.take(table, place[some], axis=2)
                if own.dtype == np.uint8:  # what comes in is less than the corner, too
                    own = own.astype(np.int16)
                    np.copyto(own, np.int16(1 << 13), where=(D.excess(h, w) > 0)[:, :, None])
                into = (into - corner).astype(own.dtype)
                if h + w < most:
                    out = into[0] + own[0]
                    for k in range(1, h + w + 1):
                        np.minimum(out, into[k] + own[k], out=out)
                else:
                    own = D.outside(np.moveaxis(own, 2, 0).astype(s.dtype), h, w, D.big(s))
                    out, probes[some] = minima.halves_of_many(into.T[:, None].astype(s.dtype), own)
                    out = out[:, 0].T
                out = out + corner
                tops[at_t], lefts[at_l] = out[: w + 1], out[w:]
                if borders:
                    kept[b_at[some] + np.arange(w + 1)[:, None]] = out[: w + 1]
        for k, (n, x) in enumerate(zip(blocks.tolist(), np.bincount(pair, probes, len(self.count)).astype(np.int64).tolist())):
            self.count[k]["blocks"] += n
            self.count[k]["probes"] += x
        values = [tops[k].item() for k in last]
        if borders:
            return [kept[x:y].reshape(-1, w) for x, y, w in zip(base, base[1:], width)]
        return values

    def whole(self) -> list[int]:
        """Distances of pairs that are one segment each, in whole costs, off their tables or by common letters of braids."""
        a, b = (np.array([x[k][0] for x in self.segments]) for k in (0, 1))
        m, n, place = self.size[a], self.size[b], self.place[self._find(a, b)]
        out = np.empty(len(a), np.int64)
        order = np.lexsort((n, m))
        nu = sum(S.copies(self.s))
        for lo, hi in _runs(m[order], n[order]):
            some = order[lo:hi]
            h, w = int(m[some[0]]), int(n[some[0]])
            own = self.pool[h, w]
            if isinstance(own, Braids):
                lcs = nu * w - (own.strands[place[some], nu * h :] < nu * w).sum(axis=1)
                out[some] = h + w - lcs * ((self.s.delete + self.s.insert) // nu)
            else:
                out[some] = own.tables[h, w, place[some]]
        return out.tolist()

    def tables(self, k: int) -> dict[tuple[str, str], np.ndarray]:
        """The matrices of a pair's segments, by their texts."""
        far, out = D.big(self.s), {}
        for u in set(self.segments[k][0].tolist()):
            for v in set(self.segments[k][1].tolist()):
                h, w = int(self.size[u]), int(self.size[v])
                d = self.pool[h, w].dense(self.place[self._find(np.array([u]), v)])[:, :, 0]
                out[self.text[u], self.text[v]] = D.outside(d.astype(self.s.dtype), h, w, far)
        return out


def fits(a: cuts.Cut, b: cuts.Cut) -> bool:
    """May a pair be part of a batch: its blocks are small, and not too many for one."""
    return len(a.segments) * len(b.segments) <= BLOCKS and side(a, b) <= WIDE and len(set(a.segments)) * len(set(b.segments)) * side(a, b) ** 2 <= BYTES // 2


def side(a: cuts.Cut, b: cuts.Cut) -> int:
    """Inputs of the largest block."""
    return sum(max(c.size[v] for v in set(c.segments)) for c in (a, b)) + 1


def batches(pairs: list[tuple[cuts.Cut, cuts.Cut]], scoring: Scoring, recursion: str = "one_sided", form: str = "dense", merge: str = "monge"):
    """(number of the first pair, batch with its tables built), one after another."""
    todo, at = [], 0
    while at < len(pairs):
        n, blocks = 0, 0
        while at + n < len(pairs) and n < PAIRS and (not n or blocks + len(pairs[at + n][0].segments) * len(pairs[at + n][1].segments) <= BLOCKS):
            blocks += len(pairs[at + n][0].segments) * len(pairs[at + n][1].segments)
            n += 1
        todo.append((at, n))
        at += n
    todo.reverse()
    while todo:
        at, n = todo.pop()
        b = Batch(pairs[at : at + n], scoring, recursion, form, merge)
        if b.bytes > BYTES and n > 1:
            todo += [(at + n // 2, n - n // 2), (at, n // 2)]
            continue
        b.build()
        yield at, b


def distances(pairs: list[tuple[cuts.Cut, cuts.Cut]], scoring: Scoring, recursion: str = "one_sided", borders: bool = False, form: str = "dense", merge: str = "monge", most: int = 1 << 30) -> list[tuple]:
    """(distance in numerators, or the borders, and counters) of each pair of cuts."""
    return [x for _, b in batches(pairs, scoring, recursion, form, merge) for x in zip(b.sweep(borders, most), b.count)]
