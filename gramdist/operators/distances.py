"""Distances of pairs of strings: the block method, its two main forms, the baselines, the router."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import blocks as B
from ..functions import dp
from ..functions import succinct as S
from ..plans import planner
from ..scoring import Scoring
from ..session import parts, workers


def with_texts(pairs: DataFrame, strings: DataFrame) -> DataFrame:
    """(pair_id, a, b) of (pair_id, a_id, b_id)."""
    s = strings.select("string_id", "text")
    a = s.withColumnsRenamed({"string_id": "a_id", "text": "a"})
    b = s.withColumnsRenamed({"string_id": "b_id", "text": "b"})
    return pairs.join(a, "a_id").join(b, "b_id").select("pair_id", "a", "b")


def spread(pairs: DataFrame) -> DataFrame:
    """Deal pairs out evenly: their costs differ by orders of magnitude, and neighbours tend to cost alike. There are
    four tasks for each shuffle partition of the session (adaptive execution doesn't merge them), so that a task
    that drew dear pairs doesn't hold up the stage."""
    return pairs.repartition(4 * parts(pairs.sparkSession), F.xxhash64("pair_id"))


LETTERS = 1 << 20  # letters, or an eighth as many pairs, that a kernel of many pairs gets at a time


def by_kernel(pairs: DataFrame, make: Callable[[], Callable[[str, str], tuple]], denominator: int = 1) -> DataFrame:
    """pairs (pair_id, a, b) through a kernel (a, b) -> (distance, counters); make() is called once a task, so what a
    kernel remembers is shared by the task's pairs. A null string gives a null distance."""

    def each():
        kernel = make()
        return lambda some: [kernel(a, b) for a, b in some]

    return by_kernel_of_many(pairs, each, denominator)


def by_kernel_of_many(pairs: DataFrame, make: Callable[[], Callable[[list], list]], denominator: int = 1) -> DataFrame:
    """by_kernel with a kernel that takes a list of pairs."""
    workers(pairs.sparkSession)
    kind = pairs.schema["pair_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kernel = make()
        counts = pa.map_(pa.string(), pa.int64())
        for b in batches:
            for at, rows in bounded(b):
                got = dict(zip((k for k, (x, y) in enumerate(rows) if x is not None and y is not None), kernel([r for r in rows if r[0] is not None and r[1] is not None])))
                made = [got.get(k, (None, {})) for k in range(len(rows))]
                values = pa.array([None if v is None else v / denominator for v, _ in made], pa.float64())
                counters = pa.array([sorted((k, int(n)) for k, n in c.items()) for _, c in made], counts)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(rows)), values, counters], ["pair_id", "distance", "counters"])

    return pairs.select("pair_id", "a", "b").mapInArrow(run, f"pair_id {kind}, distance double, counters map<string,bigint>")


def bounded(b: pa.RecordBatch) -> Iterator[tuple[int, list[tuple]]]:
    """(first row, its and the next rows' strings) with LETTERS letters or one pair more."""
    rows, at, weight = [], 0, 0
    for k in range(b.num_rows):
        x, y = b.column(1)[k].as_py(), b.column(2)[k].as_py()
        rows.append((x, y))
        weight += 8 + len(x or "") + len(y or "")
        if weight >= LETTERS:
            yield at, rows
            rows, at, weight = [], k + 1, 0
    if rows:
        yield at, rows


def block_distance(pairs: DataFrame, scoring: Scoring | None = None, x: int | None = None, partition: str = "grammar", codec: str = "lz78", codec_b: str | None = None, form: str = "dense", how: str = "vector", recursion: str = "one_sided", merge: str = "monge", small: str | None = None) -> DataFrame:
    """The block method with all its options; x None is chosen from letters and variables of the pair. small is the form
    of the tables of pairs whose blocks are read whole."""
    s = scoring or Scoring.unit()
    kind = "arbitrary" if s.kind == "arbitrary" else "rational"

    def make():
        repo = B.Repository(s, form, recursion, merge)
        return lambda some: B.block_distances(some, s, x, partition, codec, codec_b, repo, how, form, lambda n, total: planner.side(n, total, kind), recursion, small)

    return by_kernel_of_many(spread(pairs), make, s.denominator)


def rational_distance(pairs: DataFrame, scoring: Scoring | None = None, codec: str = "lz78", codec_b: str | None = None, x: int | None = None, how: str = "vector") -> DataFrame:
    """Linear-space tables, x = N / n: braids for uniform costs, merged by divide and conquer and searched as they are;
    density points where matches cost something, dense tables where letters differ in cost."""
    s = scoring or Scoring.unit()
    form = "perm" if S.braided(s) else "points" if s.uniform else "dense"
    return block_distance(pairs, s, x, "grammar", codec, codec_b, form, how)


def arbitrary_distance(pairs: DataFrame, scoring: Scoring, codec: str = "lz78", codec_b: str | None = None, x: int | None = None, how: str = "vector") -> DataFrame:
    """Dense tables, x = (N / n)**(2/3), any cost table; merged by quadratic Monge products, searched by halving."""
    return block_distance(pairs, scoring, x, "grammar", codec, codec_b, "dense", how)


def dp_distance(pairs: DataFrame, scoring: Scoring | None = None) -> DataFrame:
    """The quadratic baseline."""
    s = scoring or Scoring.unit()
    return by_kernel(spread(pairs), lambda: lambda a, b: (dp.distance(a, b, s), {"cells": (len(a) + 1) * (len(b) + 1)}), s.denominator)


def banded_distance(pairs: DataFrame, limit, scoring: Scoring | None = None) -> DataFrame:
    """Null where the distance is more than limit (in whole costs)."""
    s = scoring or Scoring.unit()
    return by_kernel(spread(pairs), lambda: lambda a, b: (dp.banded(a, b, s, limit * s.denominator), {}), s.denominator)


def four_russians(pairs: DataFrame, scoring: Scoring | None = None, t: int | None = None, remap: bool = True) -> DataFrame:
    s = scoring or Scoring.unit()

    def make():
        from collections import Counter

        memos: dict = {}

        def kernel(a, b):
            side = t or 2
            memo = memos.setdefault(side, {})
            if len(memo) > 2_000_000:
                memo.clear()
            c: Counter = Counter()
            return B.four_russians_distance(a, b, s, side, remap, memo, c), c

        return kernel

    return by_kernel(spread(pairs), make, s.denominator)


def rle_distance(pairs: DataFrame, scoring: Scoring | None = None) -> DataFrame:
    s = scoring or Scoring.unit()
    return by_kernel_of_many(spread(pairs), lambda: lambda some: [(v, {}) for v in B.rle_distances(some, s)], s.denominator)


def lz78_distance(pairs: DataFrame, scoring: Scoring | None = None) -> DataFrame:
    """Phrase against phrase: a phrase's table is its parent phrase's with one letter more, one merge each, of braids
    where the scoring allows it: letters times phrases in all, but for a logarithm. Pairs of short phrases, whose tables a
    sweep reads whole, have dense ones, merged for many pairs together."""
    s = scoring or Scoring.unit()
    return block_distance(pairs, s, None, "phrases", "lz78", None, "perm" if S.braided(s) else "dense", small="dense")


def grammar_against_text(pairs: DataFrame, codec: str = "lz78", gap_only: bool = False, merge: str = "braid") -> DataFrame:
    return by_kernel_of_many(spread(pairs), lambda: lambda some: [(v, {}) for v in B.grammars_against_texts(some, codec, merge, gap_only)])


def boundary_values(pairs: DataFrame, x: int, codec: str = "lz78", last: bool = False) -> DataFrame:
    """Prefix distances along the block borders: (pair_id, row_end, col, value) below every row of blocks, or below the
    last one only, the whole of a against every prefix of b."""
    workers(pairs.sparkSession)
    kind = pairs.schema["pair_id"].dataType.simpleString()

    def run(batches):
        from ..functions import cuts, many
        from ..functions import grammar as G

        s = Scoring.unit()
        for rb in batches:
            for at, rows in bounded(rb):
                made = [(at + k, *[cuts.grammar_cut(G.compress(t, codec), x) for t in ab]) for k, ab in enumerate(rows) if ab[0] and ab[1]]
                little = [r for r in made if many.fits(*r[1:]) and many.side(*r[1:]) <= B.DENSE_SIDE]
                for first, batch in many.batches([r[1:] for r in little], s):
                    values = batch.sweep(borders=True)
                    yield from bordered([(*little[first + n], v) for n, v in enumerate(values)], rb)
                done = {r[0] for r in little}
                for k, ca, cb in (r for r in made if r[0] not in done):
                    borders: list = []
                    B.sweep(ca, cb, B.Repository(s), borders=borders)
                    yield from bordered([(k, ca, cb, np.array([np.concatenate([tops[0][:1], *[top[1:] for top in tops]]) for tops in borders]))], rb)

    def bordered(swept, rb):
        """Rows of some pairs' borders, by rows of blocks."""
        if not swept:
            return
        if last:
            swept = [(k, ca, cb, v[-1:]) for k, ca, cb, v in swept]
        ident = np.repeat([r[0] for r in swept], [r[3].size for r in swept])
        ends = np.concatenate([np.repeat(np.cumsum([ca.size[v] for v in ca.segments])[-len(v) :], v.shape[1]) for _, ca, _, v in swept])
        cols = np.concatenate([np.tile(np.arange(v.shape[1]), v.shape[0]) for *_, v in swept])
        values = np.concatenate([v.reshape(-1) for *_, v in swept])
        for k in range(0, len(ident), LETTERS):
            own = slice(k, k + LETTERS)
            yield pa.RecordBatch.from_arrays([rb.column(0).take(pa.array(ident[own])), *[pa.array(c[own].astype(np.int64)) for c in (ends, cols, values)]], ["pair_id", "row_end", "col", "value"])

    return spread(pairs).select("pair_id", "a", "b").mapInArrow(run, f"pair_id {kind}, row_end long, col long, value long")


def unit_distance(pairs: DataFrame) -> DataFrame:
    """(pair_id, distance, route) by the cheapest route: trivial pairs by their lengths, short ones by the built-in,
    run-rich ones by runs, long ones of small grammars by blocks, the rest by bit vectors.

    One pass over the pairs: the routes are cases of one expression, and the Python kernel gets nulls for the pairs
    of the JVM's routes. Grammars cost a pass over the text, so the kernel looks at them only where the other routes
    are dear."""
    workers(pairs.sparkSession)

    @F.pandas_udf("distance double, route string")
    def kernel(a: pd.Series, b: pd.Series, route: pd.Series, limit: pd.Series) -> pd.DataFrame:
        s = Scoring.unit()
        out = []
        for x, y, r, most in zip(a, b, route, limit):
            if x is None or y is None:
                out.append((None, None))
                continue
            v = B.priced_blocks(x, y, most, planner.block_ns, planner.side, planner.PACKED) if most > planner.WORTH_NS else None
            out.append((float(v), "blocks") if v is not None else (float(B.rle_distance(x, y, s) if r == "runs" else dp.bit_distance(x, y)), r))
        return pd.DataFrame({"distance": pd.Series([x[0] for x in out], dtype="float64"), "route": [x[1] for x in out]})

    r = planner.route(spread(pairs))
    route = F.col("route")
    trivial = F.when(F.col("a") == F.col("b"), 0).otherwise(F.greatest(F.length("a"), F.length("b"))).cast("double")
    here = route.isin("runs", "bits")
    python = kernel(F.when(here, F.col("a")), F.when(here, F.col("b")), route, F.col("price"))
    own = F.when(route == "trivial", F.struct(trivial.alias("distance"), route.alias("route"))).when(here, python)
    r = r.withColumn("_r", own.otherwise(F.struct(F.levenshtein("a", "b").cast("double").alias("distance"), route.alias("route"))))
    return r.select("pair_id", "_r.distance", "_r.route")


def bit_distance(pairs: DataFrame) -> DataFrame:
    """The quadratic table with a column in a machine number of any length: cells cost a fraction of an operation."""
    return by_kernel(spread(pairs), lambda: lambda a, b: (dp.bit_distance(a, b), {}))


auto_distance = unit_distance
