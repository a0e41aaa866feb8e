"""Cutting a string into segments that are tied to grammar symbols.

The grammar cut works on variables, not on places in the text, so it costs the size of the grammar plus the number
of segments. Every variable of length x or more has one shape:

    anchor   both children shorter than x                its text is a segment
    join     both children x or longer                   what is open between them is closed
    grower   one child x or longer, the other shorter    the short child's text is added to the open chunk at that
                                                         side, which closes at x letters or more

A chunk is the pair of the chunk before and the added child: an ordinary rule. So segments that derive a variable's
text exactly and those that derive a part of it become symbols of one grammar, and none is 2 x or longer.
"""

from __future__ import annotations

from dataclasses import dataclass

from . import grammar as G


@dataclass
class Cut:
    """Symbols (rules of the grammar and of its chunks) and the segments of the text, in order, as symbols."""

    lhs: list[int]
    rhs: list[int]
    size: list[int]
    segments: list[int]
    roles: dict[int, str]

    def starts(self) -> list[int]:
        out, at = [], 0
        for s in self.segments:
            out.append(at)
            at += self.size[s]
        return out

    def text(self, s: int) -> str:
        return G.Slp(self.lhs, self.rhs).expand(s)


def anchors(slp: G.Slp, x: int) -> list[int]:
    size = slp.lengths()
    return [v for v, n in enumerate(size) if n >= x and (slp.lhs[v] < 0 or size[slp.lhs[v]] < x and size[slp.rhs[v]] < x)]


def grammar_cut(slp: G.Slp, x: int) -> Cut:
    lhs, rhs, size = list(slp.lhs), list(slp.rhs), slp.lengths()
    n = len(slp)
    x = max(1, min(x, size[-1]))
    chunks: dict[tuple[int, int], int] = {}
    roles: dict[int, str] = {}

    def chunk(a: int, b: int) -> int:
        v = chunks.get((a, b))
        if v is None:
            v = chunks[a, b] = len(lhs)
            lhs.append(a)
            rhs.append(b)
            size.append(size[a] + size[b])
            roles[v] = "chunk"
        return v

    # head and tail: open symbols; body: closed segments as a tree of (left, symbol, right)
    shape: list = [None] * n
    for v in range(n):
        if size[v] < x:
            continue
        a, b = lhs[v], rhs[v]
        if a < 0 or size[a] < x and size[b] < x:
            shape[v] = (None, (None, v, None), None)
            roles[v] = "anchor"
        elif size[a] >= x and size[b] >= x:
            (h, left, t), (h2, right, t2) = shape[a], shape[b]
            body = left
            for s in (t, h2):
                if s is not None:
                    body = (body, s, None)
            shape[v] = (h, (body, None, right), t2)
        elif size[a] >= x:
            h, body, t = shape[a]
            t = b if t is None else chunk(t, b)
            roles.setdefault(t, "tail")
            shape[v] = (h, (body, t, None), None) if size[t] >= x else (h, body, t)
        else:
            h, body, t = shape[b]
            h = a if h is None else chunk(a, h)
            roles.setdefault(h, "head")
            shape[v] = (None, (None, h, body), t) if size[h] >= x else (h, body, t)
    head, body, tail = shape[n - 1]
    segments = [] if head is None else [head]
    stack = [body]
    while stack:
        node = stack.pop()
        if node is None:
            continue
        if isinstance(node, int):
            segments.append(node)
        else:
            left, s, right = node
            stack += [right, s, left]
    if tail is not None:
        segments.append(tail)
    return Cut(lhs, rhs, size, segments, roles)


def parts_cut(slp: G.Slp, parts: list[int], role: str) -> Cut:
    """Segments as a compressor gave them: runs, phrases, equal pieces."""
    return Cut(list(slp.lhs), list(slp.rhs), slp.lengths(), list(parts), dict.fromkeys(parts, role))


def cut(text_or_slp, x: int, partition: str = "grammar", codec: str = "lz78") -> Cut:
    """partition: grammar (any codec), uniform, runs, phrases."""
    if partition == "grammar":
        slp = G.compress(text_or_slp, codec) if isinstance(text_or_slp, str) else text_or_slp
        return grammar_cut(slp, x)
    text = text_or_slp if isinstance(text_or_slp, str) else text_or_slp.expand()
    made = {"uniform": lambda: G.uniform(text, x), "runs": lambda: G.rle(text), "phrases": lambda: G.lz78(text)}[partition]()
    return parts_cut(*made, {"uniform": "piece", "runs": "run", "phrases": "phrase"}[partition])
