"""Kernels against the plain recurrence, worked examples and each other."""

from __future__ import annotations

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gramdist.functions import blocks as B
from gramdist.functions import cuts as C
from gramdist.functions import dist as D
from gramdist.functions import dp
from gramdist.functions import grammar as G
from gramdist.functions import many
from gramdist.functions import minima as M
from gramdist.functions import succinct as S
from gramdist.plans import planner
from gramdist.scoring import Scoring, letter_classes

SKEWED = Scoring(2, 1, 3, 1, "arbitrary", True, {"a": 3}, {"b": 2}, {("a", "b"): 1, ("b", "c"): 4})
SCORINGS = [Scoring.unit(), Scoring.indel(), Scoring.rational(1, 1, 1.5), letter_classes(), SKEWED]
small = st.text("abc", max_size=14)
words = st.text("abc", min_size=1, max_size=9)


def plain(a: str, b: str, s: Scoring):
    t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i in range(len(a) + 1):
        for j in range(len(b) + 1):
            ways = []
            if i:
                ways.append(t[i - 1][j] + s.del_cost(a[i - 1]))
            if j:
                ways.append(t[i][j - 1] + s.ins_cost(b[j - 1]))
            if i and j:
                ways.append(t[i - 1][j - 1] + s.sub_cost(a[i - 1], b[j - 1]))
            t[i][j] = min(ways, default=0)
    return t[-1][-1]


@settings(max_examples=60, deadline=None)
@given(small, small, st.sampled_from(range(5)), st.integers(0, 12))
def test_table_and_band(a, b, k, limit):
    s = SCORINGS[k]
    v = plain(a, b, s)
    assert dp.distance(a, b, s) == v
    assert k or dp.bit_distance(a, b) == v
    assert dp.banded(a, b, s, limit) == (v if v <= limit else None)


@settings(max_examples=40, deadline=None)
@given(words, words, st.sampled_from(range(5)))
def test_boundary_matrices(a, b, k):
    s = SCORINGS[k]
    p, q = len(a), len(b)
    d = D.by_tables(a, b, s)
    assert d[p, q] == plain(a, b, s)
    for build in D.BUILDS.values():
        assert (build(a, b, s) == d).all()
    assert D.properties(d)["monge"]
    for method in (*M.METHODS, "vector"):
        assert (D.by_division(a, b, s, method) == d).all()


@settings(max_examples=40, deadline=None)
@given(words, words, st.sampled_from(range(3)), st.randoms())
def test_propagation_and_points(a, b, k, r):
    s = SCORINGS[k]
    p, q = len(a), len(b)
    d = D.by_tables(a, b, s)
    v = np.cumsum([r.randint(-1, 1) for _ in range(p + q + 1)])
    want = M.column_minima(v, d)
    for method in (*M.METHODS, "vector"):
        assert (M.column_minima(v, d, method) == want).all()
    points = S.Points(d, p, q, s.delete)
    f = points.dense()
    assert (points.dense(D.big(s)) == d).all()
    assert all(points.query(i, j) == f[i, j] for i in range(p + q + 1) for j in range(p + q + 1))
    assert points.mass == 2 * s.delete * (p + q)  # linear space: the density's mass
    for method in ("halves", "elimination"):
        assert (S.propagate(v, points, method) == want).all()


def test_elimination_probes_are_linear():
    for n in (16, 64, 256):
        a, b = "ab" * n, "ba" * n
        d = D.by_increments(a[:n], b[:n], Scoring.unit())
        probes: list[int] = []
        M.column_minima(np.arange(len(d)), d, "elimination", probes)
        assert probes[0] <= 10 * len(d)


@settings(max_examples=60, deadline=None)
@given(words, words, words)
def test_braids(a, a2, b):
    k = S.comb(a, b)
    whole = S.stack_rows(k, S.comb(a2, b), len(a), len(a2), len(b))
    assert (whole == S.comb(a + a2, b)).all()
    for i in range(len(b) + 1):
        for j in range(i, len(b) + 1):
            assert S.common(k, len(a), len(b), i, j) == (len(a) + j - i - plain(a, b[i:j], Scoring.indel())) // 2
    p, q = len(a), len(b)
    assert (S.unit_dist(S.comb(S.doubled(a), S.doubled(b)), p, q, D.big(Scoring.unit())) == D.by_tables(a, b, Scoring.unit())).all()


def test_merging_is_associative_and_swaps_by_reversal():
    s = Scoring.unit()
    a, b = "abcab", "bca"
    far = D.big(s)
    d = [D.by_tables(a, x, s) for x in ("b", "ca", "ab")]
    left = D.merge_columns(D.merge_columns(d[0], d[1], 5, 1, 2, far), d[2], 5, 3, 2, far)
    right = D.merge_columns(d[0], D.merge_columns(d[1], d[2], 5, 2, 2, far), 5, 1, 4, far)
    assert (left == right).all()
    assert (D.by_tables(a, b, s)[::-1, ::-1] == D.by_tables(b, a, s)).all()


@pytest.mark.parametrize("codec", list(G.CODECS))
def test_codecs(codec):
    r = random.Random(4)
    for _ in range(60):
        s = "".join(r.choice("abcd"[: r.randint(1, 4)]) for _ in range(r.randint(1, 70)))
        slp, parts = G.codec(codec)(s)
        assert slp.expand() == s and not slp.violations()
        assert codec == "lz77" or "".join(slp.expand(v) for v in parts) == s
        x = r.randint(1, len(s))
        c = C.grammar_cut(slp, x)
        t = [c.text(v) for v in c.segments]
        assert "".join(t) == s
        assert max(map(len, t)) < max(2 * x, 2) and len(t) <= 3 * len(s) / x + 2
        i = r.randint(0, len(s) - 1)
        assert slp.substr(i, 5) == s[i : i + 5]
        assert slp.fingerprints()[-1] == G.rle(s)[0].fingerprints()[-1]
        assert slp.normalised().expand() == s and G.reversed_(slp).expand() == s[::-1]
        assert G.powered(slp, 3).expand() == 3 * s and G.concatenated([slp, slp]).expand() == 2 * s


def test_entropy_coders_are_refused():
    for name in ("huffman", "arithmetic", "bwt", "nonsense"):
        with pytest.raises(G.UnsupportedCodec):
            G.compress("abc", name)


def test_example_word():
    w = G.word("fibonacci", 7)
    assert w.expand() == "abaababaabaab" and len(w) == 7
    want = {1: "a.b.a.a.b.a.b.a.a.b.a.a.b", 2: "ab.a.ab.ab.a.ab.a.ab", 3: "aba.ab.aba.aba.ab", 4: "abaab.aba.abaab", 5: "abaab.aba.abaab", 8: "abaababa.abaab", 13: "abaababaabaab"}
    for x, cut in want.items():
        c = C.grammar_cut(w, x)
        assert ".".join(c.text(v) for v in c.segments) == cut
    assert len(G.word("doubling", 40)) == 41 and G.word("doubling", 40).lengths()[-1] == 1 << 40


def test_example_block():
    d, e = D.by_tables("ABCD", "ABBD", Scoring.unit()), D.excess(4, 4)
    want = """0 1 2 3 4 . . . .
1 1 2 3 3 4 . . .
2 2 2 3 3 4 4 . .
3 3 3 3 2 3 3 4 .
4 3 2 2 1 2 2 3 4
. 4 3 3 2 2 2 3 3
. . 4 3 2 2 2 2 2
. . . 4 3 3 2 1 1
. . . . 4 3 2 1 0"""
    assert "\n".join(" ".join("." if e[i, j] else str(d[i, j]) for j in range(9)) for i in range(9)) == want


@settings(max_examples=25, deadline=None)
@given(st.text("ab", max_size=24), st.text("abc", max_size=24), st.sampled_from(range(5)), st.integers(1, 9), st.sampled_from(list(G.CODECS)), st.sampled_from(list(G.CODECS)))
def test_all_variants_agree(a, b, k, x, ca, cb):
    s = SCORINGS[k]
    v = plain(a, b, s)
    forms = ["dense"] + ["points"] * s.uniform + ["perm"] * (k < 2)
    for part in ("grammar", "uniform", "runs", "phrases"):
        for form in forms:
            for recursion in ("one_sided", "four_way"):
                repo = B.Repository(s, form, recursion)
                got, count = B.block_distance(a, b, s, x, part, ca, cb, repo)
                assert got == v
                if count and recursion == "one_sided":
                    assert count["merges"] <= count["tables"]
    assert B.rle_distance(a, b, s) == v
    if s.kind != "arbitrary":
        assert B.four_russians_distance(a, b, s, min(x, 4)) == v
    if k == 0:
        assert B.grammar_against_text(a, b, ca) == v == B.grammar_against_text(a, b, ca, "dense")
    if k == 1:
        assert B.grammar_against_text(a, b, ca, gap_only=True) == v


def test_work_follows_the_formulas():
    """Merges stay below the number of distinct pairs; blocks fall with the square of the side."""
    a, b = G.word("fibonacci", 16), G.word("fibonacci", 17)
    blocks = {}
    for x in (8, 16, 32, 64):
        repo = B.Repository(Scoring.unit())
        ca, cb = C.grammar_cut(a, x), C.grammar_cut(b, x)
        assert B.sweep(ca, cb, repo) == b.lengths()[-1] - a.lengths()[-1]
        assert repo.count["merges"] <= (len(ca.lhs)) * (len(cb.lhs))
        blocks[x] = repo.count["blocks"] * x * x
    assert max(blocks.values()) <= 4 * min(blocks.values())


def test_side_of_blocks():
    assert planner.side(10, 1000) == 100 and planner.side(10, 1000, "arbitrary") == 22 and planner.side(1000, 1000) == 1


def test_long_bit_vectors():
    r = random.Random(7)
    for n, m in ((300, 170), (64, 65), (1, 500), (128, 128)):
        a, b = ("".join(r.choice("abé𝄞") for _ in range(k)) for k in (n, m))
        assert dp.bit_distance(a, b) == dp.distance(a, b, Scoring.unit())


def test_best_window():
    r = random.Random(5)
    for _ in range(40):
        p, t = ("".join(r.choice("abc") for _ in range(n)) for n in (r.randint(1, 6), r.randint(0, 14)))
        assert B.best_window(p, t) == min(plain(p, t[i:j], Scoring.unit()) for i in range(len(t) + 1) for j in range(i, len(t) + 1))


@settings(max_examples=40, deadline=None)
@given(words, words, st.sampled_from([(1, 1, 1), (1, 1, 2), (1, 1, 1.5), (2, 1, 2), (3, 2, 1), (1, 1, 0.5)]))
def test_braids_serve_every_uniform_rational_scoring(a, b, costs):
    s = Scoring.rational(*costs)
    assert S.braided(s) and (D.by_braid(a, b, s) == D.by_tables(a, b, s)).all()


@pytest.mark.parametrize("base", [1, 32])
def test_braid_products_by_both_ways(base, monkeypatch):
    r = np.random.default_rng(1)
    for n in (1, 2, 5, 33, 70, 200):
        a, b = r.permutation(n), r.permutation(n)
        want = S.product(a, b)
        monkeypatch.setattr(S, "BASE", base)
        assert (S.product(a, b) == want).all()
        monkeypatch.undo()


def test_monge_products_read_quadratically():
    r = random.Random(3)
    for n in (40, 80, 160):
        a, b, c = ("".join(r.choice("abcde") for _ in range(n)) for _ in range(3))
        s = letter_classes(0.37)
        x, y = D.by_increments(a, b, s), D.by_increments(a, c, s)
        probes: list[int] = []
        got = M.monge_product(x[:, n:], y[: n + 1, :], probes, at_once=5000)
        assert np.allclose(got, D.min_plus(x[:, n:], y[: n + 1, :]))
        assert probes[0] <= 12 * len(x) ** 2


@pytest.mark.parametrize("form", ["perm", "points", "dense"])
def test_wide_blocks_are_searched_along_diagonals(form):
    for family, k in (("fibonacci", 15), ("thue", 9), ("doubling", 9)):
        one, two = G.word(family, k), G.word(family, k - 1)
        a, b = one.expand(), two.expand()
        for x in (20, 45, 90):
            ca, cb, repo = C.grammar_cut(one, x), C.grammar_cut(two, x), B.Repository(Scoring.unit(), form)
            assert B.sweep(ca, cb, repo) == dp.distance(a, b, Scoring.unit())
            assert x < 40 or repo.count["probes"] < len(a) * len(b)


def test_block_route_is_taken_where_it_is_cheaper():
    a, b = G.word("fibonacci", 16).expand(), G.word("fibonacci", 15).expand()
    want = dp.bit_distance(a, b)
    assert B.priced_blocks(a, b, 1e18, planner.block_ns, planner.side, 5) == want
    assert B.priced_blocks(a, b, 1.0, planner.block_ns, planner.side, 5) is None
    assert B.priced_blocks("the quick brown fox", "jumps over", 1e18, planner.block_ns, planner.side, planner.PACKED) is None


def test_runs_of_many_pairs_in_strips(monkeypatch):
    """A long pair of few runs costs no step a block of two runs, alone or among others."""
    random.seed(5)
    word = lambda: "".join(random.choice("abc") * random.randint(1, random.choice([2, 30])) for _ in range(random.randint(0, 12)))
    pairs = [(word(), word()) for _ in range(300)] + [("ab" * 40, "a" * 3000), ("", "aab"), ("aab", ""), ("a", "a\0\0b")]
    want = [dp.bit_distance(a, b) for a, b in pairs]
    monkeypatch.setattr(B, "run_block", None)
    assert B.rle_distances(pairs, Scoring.unit()) == want
    monkeypatch.setattr(B, "AT_ONCE", 500)
    assert B.rle_distances(pairs, Scoring.unit()) == want
    assert [B.rle_distance(a, b, Scoring.unit()) for a, b in pairs] == want


@pytest.mark.parametrize("k", range(len(SCORINGS)))
def test_many_pairs_share_their_merges(k, monkeypatch):
    """Pairs of small blocks, wide ones and long runs in one batch: values of the plain table, no table made on its own."""
    s = SCORINGS[k]
    random.seed(7)
    word = lambda n: "".join(random.choice("abc") for _ in range(n))
    pairs = [(word(random.randint(1, 40)), word(random.randint(1, 40))) for _ in range(60)] + [("", "ab"), ("ab", ""), ("ab" * 60, word(90)), ("a", "\0")]
    want = [dp.distance(a, b, s) for a, b in pairs]
    monkeypatch.setattr(B.Repository, "_make", None)
    for x in (1, 3, 8, 30):
        for recursion in ("one_sided", "four_way"):
            got = B.block_distances(pairs, s, x, recursion=recursion)
            assert [v for v, _ in got] == pytest.approx(want)
    assert [v for v, _ in B.block_distances(pairs, s, None, "phrases", form="perm" if S.braided(s) else "dense", small="dense")] == pytest.approx(want)
    monkeypatch.undo()
    monkeypatch.setattr(many, "BYTES", 1 << 16)
    monkeypatch.setattr(many, "BLOCKS", 400)
    got = B.block_distances(pairs, s, 4)
    assert [v for v, _ in got] == pytest.approx(want)
    one = [B.block_distance(a, b, s, 4) for a, b in pairs]
    for name in ("blocks", "distinct", "cells", "segments", "probes"):
        assert [c[name] for _, c in got] == [c[name] for _, c in one]
    assert all(0 < c["merges"] <= c["tables"] for (a, b), (_, c) in zip(pairs[:1], got))


def test_borders_of_many_pairs(monkeypatch):
    s = Scoring.unit()
    random.seed(9)
    word = lambda: "".join(random.choice("abc") for _ in range(random.randint(1, 30)))
    pairs = [(word(), word()) for _ in range(40)]
    cut = [tuple(C.grammar_cut(G.compress(t, "lz78"), 4) for t in ab) for ab in pairs]
    monkeypatch.setattr(B.Repository, "_make", None)
    for (a, b), (ca, cb), (values, _) in zip(pairs, cut, many.distances(cut, s, borders=True)):
        ends = np.cumsum([ca.size[v] for v in ca.segments]).tolist()
        rows = list(dp.table_rows(a, b, s))
        assert [v.tolist() for v in values] == [rows[e].tolist() for e in ends]


def test_a_side_moves_the_work_of_many_pairs_never_the_value(monkeypatch):
    """Blocks up to side 32 are merged in batches: no table is made on its own, whatever the side."""
    random.seed(11)
    word = lambda: "".join(random.choice("VVVCP") for _ in range(random.randint(50, 80)))
    pairs = [(word(), word()) for _ in range(12)]
    want = [dp.bit_distance(a, b) for a, b in pairs]
    monkeypatch.setattr(B.Repository, "_make", None)
    work = {}
    for x in (1, 2, 4, 8, 16, 32):
        got = B.block_distances(pairs, Scoring.unit(), x)
        assert [v for v, _ in got] == want
        work[x] = {k: sum(c[k] for _, c in got) for k in ("blocks", "merges", "entries", "probes")}
    assert work[1]["blocks"] > work[4]["blocks"] > work[32]["blocks"] and work[1]["merges"] == 0 < work[4]["merges"]
    assert work[1]["probes"] > work[32]["probes"]


@pytest.mark.parametrize("name", ["points", "braids", "halves", "elimination", "monge_merge"])
def test_variants_of_many_pairs_make_no_table_alone(monkeypatch, name):
    from gramdist.workloads import VARIANTS

    random.seed(13)
    word = lambda: "".join(random.choice("FFOP") for _ in range(random.randint(1, 12)))
    pairs = [(word(), word()) for _ in range(50)] + [("", "FO"), ("F", ""), ("é", "é")]
    v = dict(VARIANTS[name])
    held = {"recursion": v.pop("recursion", "one_sided"), "form": v.get("form", "dense"), "merge": v.pop("merge", "monge")}
    s = Scoring.unit()
    one = [B.block_distance(a, b, s, 4, repo=B.Repository(s, **held), **v) for a, b in pairs]
    monkeypatch.setattr(B.Repository, "_make", None)
    got = B.block_distances(pairs, s, 4, repo=B.Repository(s, **held), recursion=held["recursion"], **v)
    assert [x for x, _ in got] == [dp.distance(a, b, s) for a, b in pairs] == [x for x, _ in one]
    for k in ("blocks", "distinct", "segments", "cells", "probes"):
        assert [c[k] for _, c in got] == [c[k] for _, c in one]
    for k in range(len(pairs)):  # a pair alone counts what its own repository does
        monkeypatch.undo()
        (_, c), (_, w) = B.block_distances([pairs[k]], s, 4, repo=B.Repository(s, **held), recursion=held["recursion"], **v)[0], one[k]
        assert [c[x] for x in ("tables", "merges", "leaves", "entries", "points")] == [w[x] for x in ("tables", "merges", "leaves", "entries", "points")]


@pytest.mark.parametrize("merge", ["braid", "dense"])
@pytest.mark.parametrize("gap_only", [True, False])
def test_grammars_against_texts_together(monkeypatch, merge, gap_only):
    random.seed(17)
    word = lambda n: "".join(random.choice("FOP") for _ in range(random.randint(1, n)))
    pairs = [(word(12), word(12)) for _ in range(60)] + [("", "FO"), ("F", ""), (word(90), word(90)), ("é", "é𝄞")]
    want = [dp.distance(a, b, Scoring.indel() if gap_only else Scoring.unit()) for a, b in pairs]
    alone, real = [], B.grammar_against_text
    monkeypatch.setattr(B, "grammar_against_text", lambda *x: alone.append(x) or real(*x))
    assert B.grammars_against_texts(pairs, "lz78", merge, gap_only) == want
    assert len(alone) <= 3


def test_large_blocks_are_searched_for_many_pairs_together(monkeypatch):
    """At side 32 blocks have more inputs than are read whole: none is swept on its own, with the reads of one pair alone."""
    random.seed(19)
    word = lambda: "".join(random.choice("VVVCP") for _ in range(random.randint(40, 90)))
    pairs = [(word(), word()) for _ in range(14)] + [("V", word()), (word(), "C" * 70)]
    s = Scoring.unit()
    one = [B.block_distance(a, b, s, 32) for a, b in pairs]
    monkeypatch.setattr(B, "sweep", None)
    got = B.block_distances(pairs, s, 32)
    assert [v for v, _ in got] == [dp.bit_distance(a, b) for a, b in pairs]
    for k in ("blocks", "distinct", "probes"):
        assert [c[k] for _, c in got] == [c[k] for _, c in one]


@pytest.mark.parametrize("s", [Scoring.unit(), Scoring.indel(), Scoring.rational(1, 1, 1.5), Scoring.rational(3, 2, 4)])
def test_work_of_tables_of_bytes_is_that_of_wide_numbers(monkeypatch, s):
    """Tables of short segments hold bytes, longer ones or dearer costs wider numbers: same distances, same work."""
    random.seed(23)
    word = lambda n: "".join(random.choice("VCP") for _ in range(n))
    pairs = [(word(random.randint(1, 70)), word(random.randint(1, 70))) for _ in range(20)] + [("V" * 63, "C" * 63), ("V" * 64, "C" * 64)]
    cut = [tuple(C.grammar_cut(G.compress(t, "lz78"), 32) for t in ab) for ab in pairs]
    assert any(many.Batch([c], s).dtype == np.uint8 for c in cut)
    for few in ([c for c in cut if many.Batch([c], s).dtype == np.uint8], cut):
        got = many.distances(few, s, most=B.DENSE_SIDE)
        want = [(dp.distance(*(("".join(x.text(v) for v in x.segments)) for x in c), s)) for c in few]
        assert [v for v, _ in got] == want
    assert [c["probes"] for _, c in got] == [B.block_distance(a, b, s, 32)[1]["probes"] for a, b in pairs]


@settings(max_examples=60, deadline=None)
@given(st.one_of(st.text("ab. ", min_size=1, max_size=90), st.text(min_size=1, max_size=40), st.builds(lambda a, n: a * n, st.text("abc ", min_size=1, max_size=5), st.integers(1, 60))))
def test_sizes_without_rules(text):
    for c in G.SIZES:
        assert G.rule_count(text, c) == len(G.compress(text, c)), c
