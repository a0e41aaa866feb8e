"""DataFrame operators: edge cases, stores, SQL functions, streaming."""

from __future__ import annotations

import os

import pytest

from gramdist.functions import grammar as G
from gramdist.operators import distances as X
from gramdist.operators import grammars as S
from gramdist.operators import relational as R
from gramdist.operators import repository as P
from gramdist.operators import similarity as sim
from gramdist.operators.tiled import tiled_distance
from gramdist.plans import planner
from gramdist.scoring import Scoring, check_metric, cost_rows, letter_classes
from gramdist.sources import phrases, tables

PAIRS = [(0, "kitten", "sitting"), (1, "", "abc"), (2, "abc", ""), (3, "same", "same"), (4, "", ""), (5, "a" * 300, "a" * 299), (6, "xyz", "abcd"), (7, "abc", "abcdef"), (8, "né𝄞e", "ne𝄞"), (9, "tab\there", "line\nhere")]
WANT = {0: 3, 1: 3, 2: 3, 3: 0, 4: 0, 5: 1, 6: 4, 7: 3, 8: 2, 9: 5}


@pytest.fixture(scope="module")
def pairs(spark):
    return spark.createDataFrame([*PAIRS, (10, None, "a"), (11, "a", None)], "pair_id long, a string, b string")


def values(df) -> dict:
    return {r.pair_id: r.distance for r in df.collect()}


@pytest.mark.parametrize("f", [X.dp_distance, X.block_distance, X.rational_distance, X.rle_distance, X.four_russians, X.lz78_distance, X.grammar_against_text, X.bit_distance, X.unit_distance])
def test_edge_pairs(pairs, f):
    assert values(f(pairs)) == WANT | {10: None, 11: None}


def test_arbitrary_and_banded(spark, pairs):
    s = letter_classes(0.37)
    a, b = values(X.arbitrary_distance(pairs, s)), values(X.dp_distance(pairs, s))
    assert all(a[k] == pytest.approx(b[k], abs=1e-6) for k in range(10))
    assert values(X.banded_distance(pairs, 3)) == {k: (v if v <= 3 else None) for k, v in WANT.items()} | {10: None, 11: None}


def test_sql_table_forms(spark):
    p = spark.createDataFrame([x for x in PAIRS if x[0] not in (5,)], "pair_id long, a string, b string")
    assert {r.pair_id: r.distance for r in R.dp_distance_sql(p).collect()} == {k: v for k, v in WANT.items() if k != 5}
    q = p.where("length(a) > 0 AND length(b) > 0")
    assert {r.pair_id: r.distance for r in R.lightest_path(R.grid_edges(q)).collect()} == {k: WANT[k] for k in (0, 3, 6, 7, 8, 9)}


def test_boundary_values(spark):
    p = spark.createDataFrame([(1, "abaababaab", "babaab")], "pair_id long, a string, b string")
    from gramdist.functions import dp

    want = {(i, j): int(v) for i, row in enumerate(dp.table_rows("abaababaab", "babaab", Scoring.unit())) for j, v in enumerate(row)}
    rows = X.boundary_values(p, 2).collect()
    assert rows and all(want[r.row_end, r.col] == r.value for r in rows)
    assert {r.col for r in rows if r.row_end == 10} == set(range(7))
    last = X.boundary_values(p, 2, last=True).collect()
    assert sorted(last) == sorted(r for r in rows if r.row_end == 10)


def test_tiles(spark):
    a, b = "abcabba" * 9, "cbabac" * 11
    from gramdist.functions import dp

    for s in (Scoring.unit(), letter_classes(), Scoring.rational(1, 1, 1.5)):
        assert tiled_distance(spark, a, b, 3, s) == pytest.approx(dp.distance(a, b, s) / s.denominator)
    assert tiled_distance(spark, "", "abc") == 3


def test_rules_validate_annotate(spark):
    strings = spark.createDataFrame([(1, "abaababaabaab"), (2, "aaaaaaaa"), (3, ""), (4, None), (5, "x")], "string_id long, text string")
    slps = S.compress(strings, "lz78")
    assert {r.string_id for r in slps.collect()} == {1, 2, 5}
    rules = S.rules(slps)
    assert S.validate(rules).count() == 0
    assert {r.gid: r.n for r in S.annotate(rules).groupBy("gid").agg({"len": "max"}).withColumnRenamed("max(len)", "n").collect()} == {1: 13, 2: 8, 5: 1}
    assert {r.string_id: r.text for r in S.expand(S.packed(rules)).collect()} == {1: "abaababaabaab", 2: "aaaaaaaa", 5: "x"}
    bad = spark.createDataFrame([(1, 0, "letter", 97, None, None), (1, 1, "pair", None, 0, 2), (1, 2, "pair", None, 0, 0), (2, 0, "letter", 97, None, None), (2, 0, "letter", 98, None, None), (3, 0, "pair", None, 7, 7), (4, 0, "pair", 97, 1, None)], "gid long, var int, kind string, sym int, lhs int, rhs int")
    assert {(r.gid, r.problem) for r in S.validate(bad).collect()} == {(1, "order"), (2, "twice"), (3, "order"), (3, "missing child"), (4, "shape"), (4, "order"), (4, "missing child")}


def test_grammar_operators(spark):
    a = spark.createDataFrame([(1, "abab"), (2, "zz")], "string_id long, text string")
    s = S.compress(a, "lzw")
    text = lambda df: {r.string_id: r.text for r in S.expand(df).collect()}
    assert text(S.concat_slp(s, s)) == {1: "abababab", 2: "zzzz"}
    assert text(S.power_slp(s, 3)) == {1: "abab" * 3, 2: "zz" * 3}
    assert text(S.reverse_slp(s)) == {1: "baba", 2: "zz"} and text(S.normalise(s)) == {1: "abab", 2: "zz"}
    assert {r.string_id: r.text for r in S.substr(s, 1, 2).collect()} == {1: "ba", 2: "z"}
    assert S.share_grammars(s.unionByName(s)).agg({"grammars": "min"}).first()[0] == 2
    best = S.best_slp(spark.createDataFrame([(1, "a" * 64), (2, "abcabcabc")], "string_id long, text string"))
    assert {r.string_id for r in best.collect()} == {1, 2}


def test_corpus_pairs(spark):
    a = spark.createDataFrame([(1, "abababc"), (2, "ababx"), (3, "")], "string_id long, text string")
    cur, merges = S.corpus_pairs(a, 2)
    assert merges[0] == ("a", "b", 5)
    assert {r.string_id: "".join(r.tokens) for r in cur.collect()} == {1: "abababc", 2: "ababx"}


def test_grid_partition(spark):
    a = spark.createDataFrame([(1, "abababababab"), (2, "bababababa")], "string_id long, text string")
    seg = S.x_partition(a, 2)
    g = S.grid_partition(seg, seg, spark.createDataFrame([(9, 1, 2)], "pair_id long, a_id long, b_id long")).first()
    n = {r.string_id: r["count"] for r in seg.groupBy("string_id").count().collect()}
    assert g.blocks == n[1] * n[2] and g.distinct_pairs <= g.blocks


def test_repository_is_reused(spark, tmp_path):
    w = spark.createDataFrame([(1, "abcabcab"), (2, "abcab"), (3, "cabcabca")], "string_id long, text string")
    p = spark.createDataFrame([(12, 1, 2), (23, 2, 3)], "pair_id long, a_id long, b_id long")
    d, repo = P.shared_distance(p, w, 2)
    first = values(d)
    P.write_repository(repo, str(tmp_path / "r"))
    P.write_repository(repo, str(tmp_path / "r"))
    back = P.read_repository(spark, str(tmp_path / "r"))
    assert back.count() == repo.count()
    again, whole = P.shared_distance(p, w, 2, known=back)
    assert values(again) == first and whole.count() == repo.count()
    want = values(X.dp_distance(X.with_texts(p, w)))
    assert first == want


def test_metric_report(spark):
    assert check_metric(cost_rows(spark, Scoring.unit(), "abc")).count() == 0
    assert check_metric(cost_rows(spark, letter_classes(), "abei")).count() == 0
    bad = {r.axiom for r in check_metric(cost_rows(spark, Scoring(1, 1, 1, 1, "arbitrary", True, {}, {}, {("a", "b"): 9, ("b", "a"): -1}), "abc")).collect()}
    assert bad == {"nonnegative", "identity", "symmetry", "triangle"}
    t = cost_rows(spark, letter_classes(), "abe")
    assert Scoring.from_table(t, 2, 2, 2).sub_cost("a", "b") == 3


def test_similarity_join_loses_nothing(spark):
    import random

    r = random.Random(6)
    texts = list({"".join(r.choice("ab") for _ in range(r.randint(0, 9))) for _ in range(90)})
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)] + [(1000, texts[0]), (1001, None)], "string_id long, text string")
    from gramdist.functions import dp

    for k in (0, 1, 2):
        want = {(a, b) for a in texts for b in texts if a < b and dp.distance(a, b, Scoring.unit()) <= k}
        assert {(x.a, x.b) for x in sim.similarity_join(df, k).collect()} == want


def test_contained_both_ways(spark):
    pats = spark.createDataFrame([(1, "the quick brown fox jumps over")], "string_id long, text string")
    docs = spark.createDataFrame([(1, "so the quick brown fox jumped over it"), (2, "nothing of the kind here at all"), (3, None), (4, "the quick brown fox jumps over")], "string_id long, text string")
    want = {(1, 1): 2, (1, 4): 0}
    assert {(r.pattern_id, r.string_id): r.distance for r in sim.contained(pats, docs, 10).collect()} == want
    old, sim.MOST_KEYS = sim.MOST_KEYS, 0
    try:
        assert {(r.pattern_id, r.string_id): r.distance for r in sim.contained(pats, docs, 10).collect()} == want
    finally:
        sim.MOST_KEYS = old


def test_classes(spark):
    e = spark.createDataFrame([(k, k + 1) for k in range(1, 40)] + [(100, 101)], "a long, b long")
    assert {r.label for r in sim.classes(e).collect()} == {1, 100}


def test_route_and_sides(spark, pairs):
    r = {x.pair_id: x.route for x in planner.route(pairs.unionByName(spark.createDataFrame([(20, "a" * 9000 + "b" * 9000, "b" * 9000 + "a" * 8000), (21, "ab" * 400, "ba" * 400)], pairs.schema))).collect()}
    assert r[0] == "table" and r[3] == "trivial" and r[21] == "bits" and r[20] == "runs"
    x = spark.range(1).select(planner.choose_x(10, 1000).alias("a"), planner.choose_x(10, 1000, "arbitrary").alias("b"), planner.choose_x(10, 1000, power_of_two=True).alias("c")).first()
    assert (x.a, x.b, x.c) == (100, 22, 128)


def test_stores_and_sources(spark, tmp_path):
    a = spark.createDataFrame([(1, "abab\tc"), (2, "zz\\n\n1")], "string_id long, text string")
    tables.write_slp(S.compress(a, "rle"), str(tmp_path / "s"))
    assert {r.text for r in S.expand(tables.read_slp(spark, str(tmp_path / "s"))).collect()} == {"abab\tc", "zz\\n\n1"}
    for fmt in ("json", "orc", "csv"):
        w = a.write.option("header", True).option("quoteAll", True).option("escape", '"')
        w.format(fmt).save(str(tmp_path / fmt))
        got = tables.read_strings(spark, fmt, str(tmp_path / fmt), "string_id", "text")
        assert {r.string_id for r in got.collect()} == {1, 2}
    os.mkdir(tmp_path / "p")
    with open(tmp_path / "p" / "x.phrases", "w", encoding="utf-8") as f:
        for r in a.collect():
            for codec in ("rle", "lz78"):
                f.write("\t".join([str(r.string_id), codec, *phrases.encode(r.text, codec)]) + "\n")
    spark.dataSource.register(phrases.PhraseSource)
    got = spark.read.format("slp_phrases").load(str(tmp_path / "p")).collect()
    assert sorted((r.string_id, r.text) for r in got) == sorted([(1, "abab\tc"), (2, "zz\\n\n1")] * 2)


def test_sql_functions(spark):
    from gramdist.functions.udfs import min_plus, register_all

    assert "edit_distance" in register_all(spark)
    r = spark.sql("SELECT edit_distance('kitten', 'sitting') d, edit_distance_w('ab', 'b', map('del', 2.0D, 'ins', 2.0D, 'sub', 2.0D, 'a>', 5.0D)) w, slp_expand(slp_of('abab', 'lz78')) t, slp_ratio('aaaaaaaa', 'rle') q").first()
    assert (r.d, r.w, r.t, r.q) == (3, 4, "abab", 2)
    assert spark.sql("SELECT array_join(collect_list(piece), '') t FROM segments('abaababaabaab', 3)").first().t == "abaababaabaab"
    assert spark.sql("SELECT count(*) n FROM rules('abab', 'lzw')").first().n == len(G.compress("abab", "lzw"))
    assert spark.sql("SELECT max_by(value, i + j) v FROM dp_cells('abc', 'abd')").first().v == 1
    assert spark.sql("SELECT w FROM dist_cells('ABCD', 'ABBD') WHERE i = 4 AND j = 4").first().w == 1
    assert spark.sql(f"SELECT {min_plus('v', 'm', '2')} x FROM (SELECT array(1, 5) v, array(3, 9, 0, 1) m)").first().x == [4, 6]


def test_streams(spark, tmp_path):
    from gramdist.streaming import events as E

    rows = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    rows.repartition(4).write.parquet(str(tmp_path / "e"))
    batch = {r.string_id: r.text for r in _event_words(spark).collect()}
    out = E.run_once(E.running_distance(E.read_events(spark, str(tmp_path / "e"), 100, "60 days"), "VCP"), "update").collect()
    from gramdist.functions import dp

    assert {r.user_id: r.distance for r in out} == {u: dp.distance(t, "VCP", Scoring.unit()) for u, t in batch.items()}
    days = E.run_once(E.window_strings(E.read_events(spark, str(tmp_path / "e"), 100), "1 day")).collect()
    assert days and all(r.text for r in days)
    sessions = E.run_once(E.session_strings(E.read_events(spark, str(tmp_path / "e"), 100), "6 hours")).collect()
    assert sessions
    m = E.fold_pieces(["VC", "", "PS", "C"], "VCP")
    assert m[5, 3] == dp.distance("VCPSC", "VCP", Scoring.unit())


def _event_words(spark):
    from gramdist.workloads import event_words

    return event_words(spark, "/root/testdata/sf0.001")


def test_near_copies_are_paired_from_whole_texts(spark):
    """Copies with a word changed anywhere, at the front too, go together; strangers don't."""
    import random

    from gramdist.operators import similarity as sim

    r = random.Random(8)
    rows = []
    for k in range(120):
        w = [f"w{r.randrange(5000)}" for _ in range(200)]
        rows.append((2 * k, " ".join(w)))
        w[r.choice([0, 1, 100, 199])] = "changed"
        rows.append((2 * k + 1, " ".join(w)))
    got = {(x.a_id, x.b_id) for x in sim.shared_minima(spark.createDataFrame(rows, "string_id long, text string")).collect()}
    assert len(got & {(2 * k, 2 * k + 1) for k in range(120)}) >= 117 and all(a + 1 == b and a % 2 == 0 for a, b in got)


def test_grammars_leave_a_task_in_bounded_batches(spark, monkeypatch):
    """Many grammars in one batch are never all Python objects at once; the start's fingerprint is the last variable's."""
    import pyarrow as pa

    from gramdist.operators import grammars as S

    sizes, batch_of = [], S._batch
    monkeypatch.setattr(S, "_batch", lambda rows, *x: sizes.append(len(rows)) or batch_of(rows, *x))
    monkeypatch.setattr(S, "AT_ONCE", 50)
    rows = pa.RecordBatch.from_pydict({"string_id": list(range(40)), "lhs": [[-1, -1, 0]] * 40, "rhs": [[97, 98, 1]] * 40})
    got = pa.Table.from_batches(S._pieces(((i, 0, len(l)) for i, l, r in S._rows(rows, "string_id", "lhs", "rhs")), ["a", "b", "n"], [S.I64] * 3, lambda row: row[2]))
    assert got.num_rows == 40 and max(sizes) == 17 and len(sizes) == 3
    monkeypatch.undo()
    g = S.compress(spark.createDataFrame([(1, "abaababa"), (2, "b"), (3, "aaaaaaa")], "string_id long, text string"), "balanced")
    last = {r.string_id: (r.fp1, r.fp2, r.len) for r in S.fingerprints(g).orderBy("string_id", "var").collect()}
    assert {r.string_id: (r.fp1, r.fp2, r.len) for r in S.start_fingerprints(g).collect()} == last


def test_unit_tiles_are_bit_vectors_of_joined_pieces(spark, monkeypatch):
    """Tiles give the table's value however pieces are cut, and neighbouring pieces make few rounds."""
    import random

    import numpy as np

    from gramdist.functions import dp
    from gramdist.operators import tiled

    r = random.Random(4)
    a, b = ("".join(r.choice("VCPF") for _ in range(n)) for n in (700, 530))
    full = np.array([[dp.bit_distance(a[:i], b[:j]) for j in range(30)] for i in range(30)])
    for i, j, p, q in ((0, 0, 29, 29), (3, 7, 1, 1), (9, 2, 8, 20), (11, 12, 17, 1), (1, 20, 20, 9)):  # tiles from their borders
        low, right = dp.bit_tile(a[i : i + p], b[j : j + q], full[i, j : j + q + 1], full[i : i + p + 1, j])
        assert low.tolist() == full[i + p, j : j + q + 1].tolist() and right.tolist() == full[i : i + p + 1, j + q].tolist()
    made, real = [], tiled.kept
    monkeypatch.setattr(tiled, "kept", lambda df: made.append(1) or real(df))
    for side in (100, 1 << 16):
        made.clear()
        monkeypatch.setattr(tiled, "SIDE", side)
        assert tiled.tiled_distance(spark, a, b, 12) == dp.bit_distance(a, b)
        assert side == 100 or len(made) <= 9


def test_runs_are_taken_by_many_pairs_at_once(spark, monkeypatch):
    from gramdist.functions import blocks as B
    from gramdist.functions import dp

    words = [("R" * k + "N" * (900 - k) + "A" * (k % 7), "N" * (5 * k) + "R" * 40) for k in range(60)] + [(None, "a"), ("", "RN")]
    df = spark.createDataFrame([(k, *w) for k, w in enumerate(words)], "pair_id long, a string, b string")
    monkeypatch.setattr(X, "LETTERS", 5_000)
    kernel = X.by_kernel_of_many

    def counted(pairs, make, denominator=1):
        def each():
            own = make()
            return lambda some: [(v, {"at_once": len(some)}) for v, _ in own(some)]

        return kernel(pairs, each, denominator)

    monkeypatch.setattr(X, "by_kernel_of_many", counted)
    rows = X.rle_distance(df).collect()
    sizes = [r.counters["at_once"] for r in rows if r.counters]
    assert max(sizes) > 1
    assert {r.pair_id: r.distance for r in rows} == {k: None if a is None else dp.bit_distance(a, b) for k, (a, b) in enumerate(words)}
    assert B.rle_distances([w for w in words if w[0] is not None], Scoring.unit()) == [dp.bit_distance(a, b) for a, b in words if a is not None]


def test_sizes_are_those_of_the_grammars(spark):
    words = [(1, "abab abab\nabc"), (2, ""), (3, None), (4, "a" * 77), (5, "né𝄞e né𝄞e"), (5, "x")]
    df = spark.createDataFrame(words, "string_id long, text string")
    codecs = ("rle", "lz78", "lzw", "words", "balanced", "lz77")
    got = S.sizes(df, codecs)
    assert got.rdd.getNumPartitions() > 1
    want = [(r.string_id, r.codec, r.variables, r.letters) for c in codecs for r in S.stats(S.compress(df, c)).collect()]
    assert sorted(tuple(r) for r in got.collect()) == sorted(want)


def test_work_by_side_of_the_operator_is_that_of_the_pairs(spark):
    from gramdist.functions import blocks as B

    words = [("VCPCV" * k, "CVPV" * (k + 1)) for k in range(1, 12)]
    df = spark.createDataFrame([(k, *w) for k, w in enumerate(words)], "pair_id long, a string, b string")
    for x in (2, 32):
        got = {r.pair_id: (r.distance, r.counters["blocks"], r.counters["distinct"], r.counters["probes"]) for r in X.block_distance(df, None, x).collect()}
        for k, (a, b) in enumerate(words):
            v, c = B.block_distance(a, b, Scoring.unit(), x)
            assert got[k] == (v, c["blocks"], c["distinct"], c["probes"])


def test_unit_tiles_in_the_jvm_give_the_tables_borders(spark):
    """Tiles anywhere in a table, of none to many common letters, shorter than a word and higher than all bits of a vector."""
    import random

    import numpy as np
    from pyspark.sql import functions as F

    from gramdist.functions import dp, jvm

    r = random.Random(5)
    rows, want = [], []

    def tile(a, b, above, before, below, after):
        given = [bytes(np.diff(x).astype(np.int8)) for x in (above, before)]
        rows.append((len(rows), a, b, *map(bytearray, given), int(before[-1])))
        want.append(int(below[-1]).to_bytes(8, "big") + b"".join(bytes(np.diff(x).astype(np.int8)) for x in (below, after)))

    for letters, others in (("ab", "ab"), ("VSCEP", "FOP"), ("abc", "xyz"), ("abcdefghijklmnop", "hijklmnopqrst"), ("aé日𝒳", "a日𝒳z"), ("q", "q")):
        a, b = ("".join(r.choice(x) for _ in range(n)) for x, n in ((letters, 270), (others, 330)))
        full = np.array(list(dp.table_rows(a, b, Scoring.unit())))
        for i, j, p, q in ((0, 0, 270, 330), (13, 7, 1, 1), (100, 20, 64, 5), (3, 200, 65, 130), (40, 300, 200, 1), (250, 1, 2, 300)):
            tile(a[i : i + p], b[j : j + q], full[i, j : j + q + 1], full[i : i + p + 1, j], full[i + p, j : j + q + 1], full[i : i + p + 1, j + q])
    a, b = ("".join(r.choice(x) for _ in range(n)) for x, n in (("VSCEP", 20001), ("FOP", 9000)))
    above, before = np.arange(9001), np.arange(20002)
    tile(a, b, above, before, *dp.bit_tile(a, b, above, before))
    df = spark.createDataFrame(rows, "id int, a string, b string, top binary, left binary, at long")
    got = {x.id: bytes(x.v) for x in df.select("id", F.call_function(jvm.unit_tile(spark), "a", "b", "top", "left", "at").alias("v")).collect()}
    assert [got[k] for k in range(len(want))] == want
