"""Functions and table functions for SQL: register_all(spark)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..scoring import Scoring
from ..session import workers
from . import cuts, dp
from . import dist as D
from . import grammar as G

SLP_TYPE = "struct<size:int,length:long,lhs:array<int>,rhs:array<int>>"


def _known(costs) -> Scoring:
    """A cost map: del, ins, sub are the defaults; "a>b" replaces, "a>" deletes, ">b" inserts."""
    c = dict(costs or {})
    d, i, r = c.pop("del", 1.0), c.pop("ins", 1.0), c.pop("sub", 1.0)
    pairs = [(k.partition(">")[0], k.partition(">")[2], v) for k, v in c.items()]
    return Scoring(d, i, r, 1, "arbitrary", True, {a: v for a, b, v in pairs if a and not b}, {b: v for a, b, v in pairs if b and not a}, {(a, b): v for a, b, v in pairs if a and b})


def make() -> dict:
    @F.pandas_udf("double")
    def edit_distance(a: pd.Series, b: pd.Series) -> pd.Series:
        s = Scoring.unit()
        return pd.Series([None if x is None or y is None else float(dp.distance(x, y, s)) for x, y in zip(a, b)])

    @F.pandas_udf("double")
    def edit_distance_w(a: pd.Series, b: pd.Series, costs: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else float(dp.distance(x, y, _known(c))) for x, y, c in zip(a, b, costs)])

    @F.pandas_udf(SLP_TYPE)
    def slp_of(text: pd.Series, codec: pd.Series) -> pd.DataFrame:
        out = [G.compress(t, c) if t else None for t, c in zip(text, codec)]
        return pd.DataFrame({"size": [len(s) if s else 0 for s in out], "length": [s.lengths()[-1] if s else 0 for s in out], "lhs": [s.lhs if s else [] for s in out], "rhs": [s.rhs if s else [] for s in out]})

    @F.pandas_udf("string")
    def slp_expand(slp: pd.DataFrame) -> pd.Series:
        return pd.Series([G.Slp(list(a), list(b)).expand() if len(a) else "" for a, b in zip(slp["lhs"], slp["rhs"])])

    @F.pandas_udf("double")
    def slp_ratio(text: pd.Series, codec: pd.Series) -> pd.Series:
        return pd.Series([len(t) / len(G.compress(t, c)) if t else None for t, c in zip(text, codec)])

    return {"edit_distance": edit_distance, "edit_distance_w": edit_distance_w, "slp_of": slp_of, "slp_expand": slp_expand, "slp_ratio": slp_ratio}


@F.udtf(returnType="seg_no int, start int, len int, piece string")
class Segments:
    """segments(text, x): the grammar cut of a text."""

    def eval(self, text: str, x: int) -> Iterator[tuple]:
        if text:
            c = cuts.grammar_cut(G.compress(text, "lz78"), x)
            for k, (s, at) in enumerate(zip(c.segments, c.starts())):
                yield k, at, c.size[s], c.text(s)


@F.udtf(returnType="var int, lhs int, rhs int, sym int")
class Rules:
    """rules(text, codec): the grammar of a text."""

    def eval(self, text: str, codec: str) -> Iterator[tuple]:
        if text:
            s = G.compress(text, codec)
            for v, (a, b) in enumerate(zip(s.lhs, s.rhs)):
                yield (v, None, None, b) if a < 0 else (v, a, b, None)


@F.udtf(returnType="i int, j int, value double")
class DpCells:
    """dp_cells(a, b): every prefix distance."""

    def eval(self, a: str, b: str) -> Iterator[tuple]:
        for i, row in enumerate(dp.table_rows(a, b, Scoring.unit())):
            for j, v in enumerate(row):
                yield i, j, float(v)


@F.udtf(returnType="i int, j int, w double")
class DistCells:
    """dist_cells(a, b): the boundary matrix of one block, entries with a path."""

    def eval(self, a: str, b: str) -> Iterator[tuple]:
        if a and b:
            d, e = D.by_increments(a, b, Scoring.unit()), D.excess(len(a), len(b))
            for i in range(len(d)):
                for j in range(len(d)):
                    if not e[i, j]:
                        yield i, j, float(d[i, j])


def register_all(spark: SparkSession) -> list[str]:
    workers(spark)
    made = make()
    for name, f in made.items():
        spark.udf.register(name, f)
    tables = {"segments": Segments, "rules": Rules, "dp_cells": DpCells, "dist_cells": DistCells}
    for name, f in tables.items():
        spark.udtf.register(name, f)
    return [*made, *tables]


def min_plus(values: str, matrix: str, width: str) -> str:
    """SQL text: column minima of values[i] + matrix[i * width + j], as an array expression without Python."""
    return f"transform(sequence(0, {width} - 1), j -> array_min(transform(sequence(0, size({values}) - 1), i -> {values}[i] + {matrix}[i * {width} + j])))"


__all__ = ["min_plus", "register_all"]
