"""The quadratic baseline: the table of prefix distances, a row at a time."""

from __future__ import annotations

import numpy as np

from ..scoring import Scoring


class Letters:
    """Costs of one scoring for many strings: replacement rows are made once per letter and string."""

    def __init__(self, scoring: Scoring, a: str, b: str):
        self.scoring, self.b = scoring, b
        self.deletes, self.inserts = scoring.vectors(a, b)
        self.rows: dict[str, np.ndarray] = {}
        self.codes = np.frombuffer(b.encode("utf-32-le"), np.uint32)

    def row(self, x: str) -> np.ndarray:
        r = self.rows.get(x)
        if r is None:
            s = self.scoring
            if s.uniform:
                r = np.full(len(self.b), s.replace, s.dtype)
                if s.free_match:
                    r[self.codes == ord(x)] = 0
            else:
                r = s.row(x, self.b)
            self.rows[x] = r
        return r


def table_rows(a: str, b: str, scoring: Scoring):
    """Rows of the table. Within a row the chain of insertions is a running minimum of (candidate - insertions so far)."""
    c = Letters(scoring, a, b)
    run = np.r_[np.zeros(1, c.inserts.dtype), np.cumsum(c.inserts)]
    row = run.copy()
    yield row
    for x, d in zip(a, c.deletes):
        best = row + d
        best[1:] = np.minimum(best[1:], row[:-1] + c.row(x))
        row = np.minimum.accumulate(best - run) + run
        yield row


def distance(a: str, b: str, scoring: Scoring):
    row = None
    for row in table_rows(a, b, scoring):
        pass
    return row[-1].item()


def last_row(a: str, b: str, scoring: Scoring) -> np.ndarray:
    row = None
    for row in table_rows(a, b, scoring):
        pass
    return row


def banded(a: str, b: str, scoring: Scoring, limit) -> float | None:
    """The distance if it is at most limit, else None: only cells near enough to the diagonal, with an early stop.

    Every step off the diagonal costs at least the cheapest gap, so cells further than limit / gap can't matter.
    """
    dels, ins = scoring.vectors(a, b)
    gap = min([*dels, *ins], default=1)
    if gap <= 0:
        d = distance(a, b, scoring)
        return d if d <= limit else None
    width = int(limit // gap)
    if abs(len(a) - len(b)) > width:
        return None
    run = np.r_[np.zeros(1, ins.dtype), np.cumsum(ins)]
    c = Letters(scoring, a, b)
    far = (limit + 1) * 2 + scoring.largest
    row = np.where(np.arange(len(b) + 1) <= width, run, far)
    for i, (x, d) in enumerate(zip(a, dels), 1):
        lo, hi = max(0, i - width), min(len(b), i + width)
        best = row[lo : hi + 1] + d
        s = max(lo, 1)
        best[s - lo :] = np.minimum(best[s - lo :], row[s - 1 : hi] + c.row(x)[s - 1 : hi])
        row = np.full(len(b) + 1, far, row.dtype)
        row[lo : hi + 1] = np.minimum.accumulate(best - run[lo : hi + 1]) + run[lo : hi + 1]
        if row.min() > limit:
            return None
    return row[-1].item() if row[-1] <= limit else None


def letter_bits(text: str) -> dict[str, int]:
    """For each letter of a text, a number with the bits of its places."""
    codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    return {chr(c): int.from_bytes(np.packbits(codes == c, bitorder="little").tobytes(), "little") for c in np.unique(codes).tolist()}


def bit_distance(a: str, b: str) -> int:
    """Unit distance with a whole column of the table in one long number: neighbouring cells differ by at most one,
    so a column is two bit vectors (where it rises, where it falls) and a letter a dozen operations on them."""
    if len(a) < len(b):
        a, b = b, a
    if not b:
        return len(a)
    m = len(a)
    places, every, last = letter_bits(a), (1 << m) - 1, 1 << (m - 1)
    rise, fall, score = every, 0, m
    for c in b:
        same = places.get(c, 0)
        diagonal = same | fall
        across = ((((same & rise) + rise) & every) ^ rise) | same
        up = fall | (every ^ (across | rise))
        down = rise & across
        if up & last:
            score += 1
        elif down & last:
            score -= 1
        up = ((up << 1) & every) | 1
        down = (down << 1) & every
        rise = down | (every ^ (diagonal | up))
        fall = up & diagonal
    return score


def _number(flags: np.ndarray) -> int:
    return int.from_bytes(np.packbits(flags, bitorder="little").tobytes(), "little")


def _flags(v: int, m: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(v.to_bytes(-(-m // 8), "little"), np.uint8), bitorder="little")[:m]


def bit_tile(a: str, b: str, top: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Last row and last column of a tile of the unit table from the values above it and to its left (both from the
    shared corner on): bit_distance with borders that may also stay level or fall."""
    m, down = len(a), np.diff(left)
    rise, fall = _number(down > 0), _number(down < 0)
    places, every, shift = letter_bits(a), (1 << m) - 1, m - 1
    steps = []
    for c, enter in zip(b, np.diff(top).tolist()):
        same = places.get(c, 0)
        diagonal = same | fall
        if enter < 0:
            same |= 1
        across = ((((same & rise) + rise) & every) ^ rise) | same
        up = fall | (every ^ (across | rise))
        low = rise & across
        steps.append((up >> shift) - (low >> shift))
        up, low = (up << 1) & every, (low << 1) & every
        if enter > 0:
            up |= 1
        elif enter < 0:
            low |= 1
        rise = low | (every ^ (diagonal | up))
        fall = up & diagonal
    last = np.cumsum(np.r_[left[-1], np.array(steps, left.dtype)])
    right = np.cumsum(np.r_[top[-1], _flags(rise, m).astype(left.dtype) - _flags(fall, m).astype(left.dtype)])
    return last.astype(top.dtype), right.astype(left.dtype)
