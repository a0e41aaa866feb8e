"""Straight-line programs in packed form, and the compressors that build them.

A program is two lists over its variables: lhs[v] < 0 marks a letter with code point rhs[v], any other variable
derives the texts of lhs[v] and rhs[v], both smaller than v. The last variable is the start.
"""

from __future__ import annotations

import re
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np

MOD = ((1 << 31) - 1, (1 << 31) - 19)
BASE = (911_382_323 % MOD[0], 972_663_749 % MOD[1])


class UnsupportedCodec(ValueError):
    """Raised for coders whose output is no small grammar."""


@dataclass
class Slp:
    lhs: list[int]
    rhs: list[int]

    def __len__(self) -> int:
        return len(self.lhs)

    def lengths(self) -> list[int]:
        out: list[int] = []
        for a, b in zip(self.lhs, self.rhs):
            out.append(1 if a < 0 else out[a] + out[b])
        return out

    def depths(self) -> list[int]:
        out: list[int] = []
        for a, b in zip(self.lhs, self.rhs):
            out.append(0 if a < 0 else 1 + max(out[a], out[b]))
        return out

    def texts(self, most: int | None = None) -> list[str | None]:
        """The text of every variable; those longer than most are left out."""
        size, out = self.lengths(), []
        for v, (a, b) in enumerate(zip(self.lhs, self.rhs)):
            out.append(None if most is not None and size[v] > most else chr(b) if a < 0 else out[a] + out[b])
        return out

    def expand(self, v: int | None = None) -> str:
        """The text of a variable (the start), without recursion."""
        out, stack = [], [len(self) - 1 if v is None else v]
        while stack:
            v = stack.pop()
            if self.lhs[v] < 0:
                out.append(chr(self.rhs[v]))
            else:
                stack += [self.rhs[v], self.lhs[v]]
        return "".join(out)

    def substr(self, start: int, count: int) -> str:
        """count letters from start, visiting only the variables that overlap them."""
        size, out, stack = self.lengths(), [], [(len(self) - 1, 0)]
        end = start + count
        while stack:
            v, at = stack.pop()
            if at >= end or at + size[v] <= start:
                continue
            if self.lhs[v] < 0:
                out.append(chr(self.rhs[v]))
            else:
                stack += [(self.rhs[v], at + size[self.lhs[v]]), (self.lhs[v], at)]
        return "".join(out)

    def violations(self) -> list[str]:
        out = []
        for v, (a, b) in enumerate(zip(self.lhs, self.rhs)):
            if a >= 0 and not (a < v and 0 <= b < v):
                out.append(f"{v}: child not before it")
        return out

    def fingerprints(self) -> list[tuple[int, int, int]]:
        """(hash, hash, length) of every variable's text: equal texts agree, whatever grammar they come from."""
        (m, n), size = MOD, self.lengths()
        one: list[int] = []
        two: list[int] = []
        power_one: list[int] = []
        power_two: list[int] = []
        for a, b in zip(self.lhs, self.rhs):
            if a < 0:
                one.append(b % m + 1)
                two.append(b % n + 1)
                power_one.append(BASE[0])
                power_two.append(BASE[1])
            else:
                p, q = power_one[b], power_two[b]
                one.append((one[a] * p + one[b]) % m)
                two.append((two[a] * q + two[b]) % n)
                power_one.append(power_one[a] * p % m)
                power_two.append(power_two[a] * q % n)
        return list(zip(one, two, size))

    def normalised(self) -> Slp:
        """Without variables that the start doesn't reach; equal rules once; numbered in order of use."""
        b, to = Builder(), {}
        need, stack = set(), [len(self) - 1]
        while stack:
            v = stack.pop()
            if v not in need:
                need.add(v)
                if self.lhs[v] >= 0:
                    stack += [self.lhs[v], self.rhs[v]]
        for v in sorted(need):
            to[v] = b.letter(self.rhs[v]) if self.lhs[v] < 0 else b.pair(to[self.lhs[v]], to[self.rhs[v]])
        return b.done(to[len(self) - 1])


class Builder:
    """Rules without repeats: the same pair gives the same variable."""

    def __init__(self):
        self.lhs: list[int] = []
        self.rhs: list[int] = []
        self.height: list[int] = []
        self.size: list[int] = []
        self.known: dict[tuple[int, int], int] = {}

    def _add(self, a: int, b: int) -> int:
        v = self.known.get((a, b))
        if v is None:
            v = self.known[a, b] = len(self.lhs)
            self.lhs.append(a)
            self.rhs.append(b)
            self.height.append(0 if a < 0 else 1 + max(self.height[a], self.height[b]))
            self.size.append(1 if a < 0 else self.size[a] + self.size[b])
        return v

    def letter(self, code: int) -> int:
        return self._add(-1, code)

    def pair(self, a: int, b: int) -> int:
        return self._add(a, b)

    def sequence(self, parts: list[int]) -> int:
        """A balanced tree over parts; equal neighbourhoods share rules."""
        known = self.known
        while len(parts) > 1:
            last = parts[len(parts) & ~1 :]
            parts = [self._add(*x) if (v := known.get(x)) is None else v for x in zip(parts[::2], parts[1::2])] + last
        return parts[0]

    def power(self, v: int, times: int) -> int:
        if times == 1:
            return v
        out = None
        while times:
            if times & 1:
                out = v if out is None else self.pair(v, out)
            times >>= 1
            if times:
                v = self.pair(v, v)
        return out

    def text(self, s: str) -> int:
        return self.sequence([self.letter(ord(c)) for c in s])

    def concat(self, a: int, b: int) -> int:
        """Join of two height-balanced trees, height-balanced again."""
        ha, hb = self.height[a], self.height[b]
        if abs(ha - hb) <= 1:
            return self.pair(a, b)
        if ha > hb:
            x, y = self.lhs[a], self.concat(self.rhs[a], b)
            if self.height[y] <= self.height[x] + 1:
                return self.pair(x, y)
            y1, y2 = self.lhs[y], self.rhs[y]
            if self.height[y1] <= self.height[x]:
                return self.concat(self.pair(x, y1), y2)
            return self.pair(self.concat(x, self.lhs[y1]), self.concat(self.rhs[y1], y2))
        x, y = self.concat(a, self.lhs[b]), self.rhs[b]
        if self.height[x] <= self.height[y] + 1:
            return self.pair(x, y)
        x1, x2 = self.lhs[x], self.rhs[x]
        if self.height[x2] <= self.height[y]:
            return self.concat(x1, self.pair(x2, y))
        return self.pair(self.concat(x1, self.lhs[x2]), self.concat(self.rhs[x2], y))

    def cover(self, v: int, start: int, end: int) -> list[int]:
        """Variables that derive letters start to end of v's text, in order."""
        out, stack = [], [(v, 0)]
        while stack:
            v, at = stack.pop()
            if at >= end or at + self.size[v] <= start:
                continue
            if start <= at and at + self.size[v] <= end:
                out.append(v)
            else:
                stack += [(self.rhs[v], at + self.size[self.lhs[v]]), (self.lhs[v], at)]
        return out

    def done(self, start: int) -> Slp:
        """The program that ends with start; later variables are dropped, or a trim is made where start isn't last."""
        if start == len(self.lhs) - 1:
            return Slp(self.lhs, self.rhs)
        return Slp(self.lhs[: start + 1], self.rhs[: start + 1])


def runs(text: str) -> list[tuple[str, int]]:
    return [(m[0][0], len(m[0])) for m in re.finditer(r"(.)\1*", text, re.S)]


def rle(text: str) -> tuple[Slp, list[int]]:
    b = Builder()
    parts = [b.power(b.letter(ord(c)), k) for c, k in runs(text)]
    return b.done(b.sequence(parts)), parts


def lz78(text: str) -> tuple[Slp, list[int]]:
    b, node, trie, parts = Builder(), None, {}, []
    for c in text:
        step = trie.get((node, c))
        if step is None:
            v = b.letter(ord(c)) if node is None else b.pair(node, b.letter(ord(c)))
            trie[node, c] = v
            parts.append(v)
            node = None
        else:
            node = step
    if node is not None:
        parts.append(node)
    return b.done(b.sequence(parts)), parts


def lzw(text: str) -> tuple[Slp, list[int]]:
    b, table, parts, now = Builder(), {}, [], None
    for c in text:
        v = b.letter(ord(c))
        if now is None:
            now = v
        elif (now, c) in table:
            now = table[now, c]
        else:
            parts.append(now)
            table[now, c] = b.pair(now, v)  # the new entry ends with the next phrase's first letter
            now = v
    parts.append(now)
    return b.done(b.sequence(parts)), parts


def lz77_factors(text: str) -> list[tuple[int, int]]:
    """(position, length) of an earlier whole occurrence, or (-1, 1) for a new letter: an online suffix automaton."""
    step, link, size, first = [{}], [-1], [0], [-1]
    last = 0

    def extend(c: str, at: int) -> None:
        nonlocal last
        cur = len(step)
        step.append({})
        link.append(0)
        size.append(size[last] + 1)
        first.append(at)
        p = last
        while p >= 0 and c not in step[p]:
            step[p][c] = cur
            p = link[p]
        if p < 0:
            link[cur] = 0
        else:
            q = step[p][c]
            if size[q] == size[p] + 1:
                link[cur] = q
            else:
                clone = len(step)
                step.append(dict(step[q]))
                link.append(link[q])
                size.append(size[p] + 1)
                first.append(first[q])
                while p >= 0 and step[p].get(c) == q:
                    step[p][c] = clone
                    p = link[p]
                link[q] = link[cur] = clone
        last = cur

    out, i = [], 0
    while i < len(text):
        state, j = 0, i
        while j < len(text) and text[j] in step[state]:
            state = step[state][text[j]]
            j += 1
        if j == i:
            out.append((-1, 1))
            j = i + 1
        else:
            out.append((first[state] - (j - i) + 1, j - i))
        for k in range(i, j):
            extend(text[k], k)
        i = j
    return out


def lz77(text: str) -> tuple[Slp, list[int]]:
    b, whole, at = Builder(), None, 0
    for pos, n in lz77_factors(text):
        if pos < 0:
            part = b.letter(ord(text[at]))
        else:
            pieces = b.cover(whole, pos, pos + n)
            part = pieces[0]
            for v in pieces[1:]:
                part = b.concat(part, v)
        whole = part if whole is None else b.concat(whole, part)
        at += n
    slp = b.done(whole).normalised()
    return slp, [len(slp) - 1]


def pairs(text: str, rounds: int = 400, least: int = 2) -> tuple[Slp, list[int]]:
    """Replace the most frequent neighbouring pair by a new variable, again and again."""
    b = Builder()
    seq = np.array([b.letter(ord(c)) for c in text], np.int64)
    for _ in range(rounds):
        if len(seq) < 2:
            break
        key = seq[:-1] << 32 | seq[1:]
        values, counts = np.unique(key, return_counts=True)
        top = int(np.argmax(counts))
        if counts[top] < least:
            break
        a, c = int(values[top] >> 32), int(values[top] & 0xFFFFFFFF)
        at = np.flatnonzero(key == values[top])
        if a == c:  # in a run of one variable only every other pair is free
            run = np.r_[0, np.cumsum(np.diff(at) != 1)]
            start = at[np.searchsorted(run, run)]
            at = at[(at - start) % 2 == 0]
        if len(at) < least:
            break
        seq[at] = b.pair(a, c)
        seq = np.delete(seq, at + 1)
    parts = seq.tolist()
    return b.done(b.sequence(parts)), parts


def dictionary(text: str, token: str = "word") -> tuple[Slp, list[int]]:
    """Every distinct token once, each a tree of its own; the text is the sequence of its tokens."""
    b = Builder()
    cut = re.findall(r"[^\n]*\n|[^\n]+", text) if token == "line" else re.findall(r"\w+|\W", text)
    made: dict[str, int] = {}
    parts = [made[t] if t in made else made.setdefault(t, b.text(t)) for t in cut]
    return b.done(b.sequence(parts)), parts


def uniform(text: str, x: int = 8) -> tuple[Slp, list[int]]:
    b, made = Builder(), {}
    parts = []
    for k in range(0, len(text), x):
        t = text[k : k + x]
        parts.append(made[t] if t in made else made.setdefault(t, b.text(t)))
    return b.done(b.sequence(parts)), parts


def balanced(text: str) -> tuple[Slp, list[int]]:
    b = Builder()
    root = b.text(text)
    return b.done(root), [root]


def word(family: str, k: int, letters: str = "ab") -> Slp:
    """Named words: fibonacci, doubling (2**k copies), thue (2**k letters), periodic (k copies of the letters)."""
    b = Builder()
    if family == "fibonacci":  # variables 1, 2 are the letters b and a; every later one joins the two before
        v, w = b.letter(ord(letters[1])), b.letter(ord(letters[0]))
        for _ in range(k - 2):
            v, w = w, b.pair(w, v)
        return b.done(w if k > 1 else v)
    if family == "doubling":
        v = b.letter(ord(letters[0]))
        for _ in range(k):
            v = b.pair(v, v)
        return b.done(v)
    if family == "thue":
        v, w = b.letter(ord(letters[0])), b.letter(ord(letters[1]))
        for _ in range(k):
            v, w = b.pair(v, w), b.pair(w, v)
        return b.done(v).normalised()
    if family == "periodic":
        return b.done(b.power(b.text(letters), k))
    raise ValueError(f"no family {family}")


CODECS = {"rle": rle, "lz78": lz78, "lzw": lzw, "lz77": lz77, "pairs": pairs, "words": dictionary, "lines": lambda t: dictionary(t, "line"), "uniform": uniform, "balanced": balanced}
NO_GRAMMAR = ("huffman", "arithmetic", "bwt")


def codec(name: str):
    """The compressor of that name; entropy coders and block sorting give no small grammar."""
    if name.lower() in NO_GRAMMAR:
        raise UnsupportedCodec(f"{name}: its output doesn't turn into a grammar of similar size")
    if name not in CODECS:
        raise UnsupportedCodec(f"{name}: unknown; known are {', '.join(CODECS)}")
    return CODECS[name]


def compress(text: str, name: str) -> Slp:
    """Any name in CODECS, or auto for the smallest of the quick ones."""
    if name == "auto":
        return min((codec(c)(text)[0] for c in ("rle", "lz78", "balanced")), key=len)
    return codec(name)(text)[0]


# --- sizes alone ----------------------------------------------------------------------------------------------------


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.int64)


class _Pairs:
    """Rules so far: how many, and the pairs among them in order, each with its number."""

    def __init__(self, keys: np.ndarray, size: int):
        """keys[k] = lhs << 32 | rhs of rule k, or -1 for a letter."""
        at = np.flatnonzero(keys >= 0)
        order = np.argsort(keys[at], kind="stable")
        self.known, self.ids, self.size = keys[at][order], at[order], size

    def add(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Numbers of the rules of these pairs, equal ones once."""
        pairs, of = np.unique(left << 32 | right, return_inverse=True)
        if not len(self.known):
            self.known, self.ids = pairs, self.size + np.arange(len(pairs))
            self.size += len(pairs)
            return self.ids[of]
        old = np.minimum(np.searchsorted(self.known, pairs), len(self.known) - 1)
        hit = self.known[old] == pairs
        own = np.where(hit, self.ids[old], self.size + np.cumsum(~hit) - 1)
        new = pairs[~hit]
        at = np.searchsorted(self.known, new)
        self.known, self.ids = np.insert(self.known, at, new), np.insert(self.ids, at, own[~hit])
        self.size += len(new)
        return own[of]

    def sequence(self, parts: np.ndarray) -> int:
        """Rules after Builder.sequence(parts), a level at once; from parts that all differ and are new, every pair is
        a new rule."""
        fresh = self.size
        while len(parts) > 1:
            even = len(parts) & ~1
            left = parts[:even:2]
            if left.min() >= fresh and len(np.unique(parts)) == len(parts):
                return self.size + len(parts) - 1
            fresh = self.size
            parts = np.concatenate([self.add(left, parts[1:even:2]), parts[even:]])
        return self.size

    def sequences(self, parts: np.ndarray, count: np.ndarray) -> np.ndarray:
        """The last rule of each of many sequences, which follow each other in parts."""
        while count.max() > 1:
            start = np.cumsum(count) - count
            place = np.arange(len(parts)) - np.repeat(start, count)
            left = np.flatnonzero((place % 2 == 0) & (place + 1 < np.repeat(count, count)))
            parts[left] = self.add(parts[left], parts[left + 1])
            parts, count = parts[place % 2 == 0], (count + 1) // 2
        return parts


def _sequence_size(parts: np.ndarray, keys: np.ndarray, size: int) -> int:
    return _Pairs(keys, size).sequence(parts)


def _built_size(b: Builder, parts: np.ndarray) -> int:
    lhs, rhs = np.array(b.lhs, np.int64), np.array(b.rhs, np.int64)
    return _sequence_size(parts, np.where(lhs < 0, -1, lhs << 32 | rhs), len(lhs))


def _rle_size(text: str) -> int:
    codes = _codes(text)
    start = np.flatnonzero(np.r_[True, codes[1:] != codes[:-1]])
    kinds, of = np.unique(codes[start] << 32 | np.diff(np.r_[start, len(codes)]), return_inverse=True)
    b = Builder()
    made = [b.power(b.letter(k >> 32), k & 0xFFFFFFFF) for k in kinds.tolist()]
    return _built_size(b, np.array(made, np.int64)[of])


def _phrase_size(text: str, overlap: bool) -> int:
    """lz78, or with overlap lzw: phrases as nodes that hold their children by letter and their number under None."""
    root = {c: {None: k} for k, c in enumerate(dict.fromkeys(text))}
    first = {c: n[None] for c, n in root.items()}
    keys, parts, size = [-1] * len(root), [], len(root)
    if overlap:
        node = root[text[0]]
        for c in text[1:]:
            if (step := node.get(c)) is None:
                parts.append(n := node[None])
                keys.append(n << 32 | first[c])
                node[c] = {None: size}
                size += 1
                node = root[c]
            else:
                node = step
        parts.append(node[None])
    else:
        seen, node = {}, None  # children of the empty phrase: letters that were one
        for c in text:
            if node is None:
                if (node := seen.get(c)) is None:
                    seen[c] = root[c]
                    parts.append(first[c])
            elif (step := node.get(c)) is None:
                keys.append(node[None] << 32 | first[c])
                node[c] = {None: size}
                parts.append(size)
                size += 1
                node = None
            else:
                node = step
        if node is not None:
            parts.append(node[None])
    return _sequence_size(np.array(parts, np.int64), np.array(keys, np.int64), size)


def _words_size(text: str) -> int:
    tokens = re.findall(r"\w+|\W", text)
    number = {t: k for k, t in enumerate(dict.fromkeys(tokens))}
    letters, parts = np.unique(_codes("".join(number)), return_inverse=True)
    made = _Pairs(np.full(len(letters), -1, np.int64), len(letters))
    roots = made.sequences(parts.astype(np.int64), np.fromiter(map(len, number), np.int64, len(number)))
    return made.sequence(roots[np.fromiter(map(number.__getitem__, tokens), np.int64, len(tokens))])


def _balanced_size(text: str) -> int:
    letters, parts = np.unique(_codes(text), return_inverse=True)
    return _sequence_size(parts.astype(np.int64), np.full(len(letters), -1, np.int64), len(letters))


SIZES = {"rle": _rle_size, "lz78": lambda t: _phrase_size(t, False), "lzw": lambda t: _phrase_size(t, True), "words": _words_size, "balanced": _balanced_size}


def rule_count(text: str, name: str) -> int:
    """How many rules compress(text, name) has; where the name is in SIZES, without making them."""
    return SIZES[name](text) if name in SIZES else len(compress(text, name))


def concatenated(parts: Iterable[Slp]) -> Slp:
    b, ends = Builder(), []
    for p in parts:
        to = []
        for a, c in zip(p.lhs, p.rhs):
            to.append(b.letter(c) if a < 0 else b.pair(to[a], to[c]))
        ends.append(to[-1])
    root = b.sequence(ends)
    return b.done(root).normalised()


def powered(p: Slp, times: int) -> Slp:
    b = Builder()
    to = []
    for a, c in zip(p.lhs, p.rhs):
        to.append(b.letter(c) if a < 0 else b.pair(to[a], to[c]))
    return b.done(b.power(to[-1], times)).normalised()


def reversed_(p: Slp) -> Slp:
    return Slp([a if a < 0 else c for a, c in zip(p.lhs, p.rhs)], [c if a < 0 else a for a, c in zip(p.lhs, p.rhs)])
