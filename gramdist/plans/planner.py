"""Cost formulas over n (variables) and N (letters), the block side they call for, and the route of a pair."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def log(c) -> Column:
    """Logarithm that is positive at 1, so bounds stay above 0 where letters and variables are as many."""
    return F.log2(F.lit(1.0) + c)


BOUNDS = {
    "block_rational": lambda n, N, x: n * n * x * log(x) + N * N * log(x) / x,
    "block_arbitrary": lambda n, N, x: n * n * x * x + N * N / x,
    "repository_rational": lambda n, N, x: n * n * x * log(x),
    "repository_arbitrary": lambda n, N, x: n * n * x * x,
    "sweep_rational": lambda n, N, x: N * N * log(x) / x,
    "sweep_arbitrary": lambda n, N, x: N * N / x,
    "best_rational": lambda n, N, x: n * N * log(N / n),
    "best_arbitrary": lambda n, N, x: F.pow(n, F.lit(2 / 3)) * F.pow(N, F.lit(4 / 3)),
    "quadratic": lambda n, N, x: N * N,
    "four_russians": lambda n, N, x: N * N / log(N),
    "four_russians_word": lambda n, N, x: N * N / (log(N) * log(N)),
    "runs_or_phrases": lambda n, N, x: n * N,
    "grammar_slow_merge": lambda n, N, x: n * F.pow(N, F.lit(1.5)),
    "grammar_fast_merge": lambda n, N, x: n * N * log(N),
    "grammar_strict_partition": lambda n, N, x: F.pow(n, F.lit(1.34)) * F.pow(N, F.lit(1.34)),
}


def bound(name: str, n, N, x=None) -> Column:
    """A method's cost formula as a column."""
    as_double = lambda c: (c if isinstance(c, Column) else F.lit(c)).cast("double")
    return BOUNDS[name](as_double(n), as_double(N), as_double(F.lit(1.0) if x is None else x))


def choose_x(n, N, kind: str = "rational", power_of_two: bool = False) -> Column:
    """ceil(N / n) for rational scoring, ceil((N / n)**(2/3)) for arbitrary, at least 1 and at most N. Rounded to a
    power of two, a string is cut at few sides whatever it is paired with; bounds change by at most a constant."""
    n, N = (c if isinstance(c, Column) else F.lit(c) for c in (n, N))
    ratio = N.cast("double") / n
    x = F.ceil(ratio if kind != "arbitrary" else F.pow(ratio, F.lit(2 / 3)))
    if power_of_two:
        x = F.pow(F.lit(2.0), F.round(F.log2(x.cast("double"))))
    return F.least(F.greatest(x.cast("long"), F.lit(1)), N.cast("long"))


def side(n: int, N: int, kind: str = "rational") -> int:
    """choose_x for numbers."""
    ratio = N / n
    return int(min(max(1, math.ceil(ratio if kind != "arbitrary" else ratio ** (2 / 3))), N))


def cheapest_x(stats: DataFrame, kind: str = "rational") -> DataFrame:
    """stats (an id, variables, letters) -> the power of two that minimises the bound, beside the closed form."""
    name = f"block_{kind}"
    grid = stats.withColumn("x", F.explode(F.expr("transform(sequence(0, cast(floor(log2(letters)) AS int)), k -> shiftleft(1L, k))")))
    grid = grid.withColumn("cost", bound(name, F.col("variables"), F.col("letters"), F.col("x")))
    keys = [c for c in stats.columns]
    best = grid.groupBy(*keys).agg(F.min_by("x", F.struct("cost", "x")).alias("best_x"), F.min("cost").alias("best_cost"))
    return best.withColumn("closed_x", choose_x(F.col("variables"), F.col("letters"), kind))


def run_count(c: Column) -> Column:
    """Runs of equal letters, without leaving the JVM."""
    return F.length(F.regexp_replace(c, r"(?s)(.)\1+", "$1"))


# Measured nanoseconds: a cell of the built-in, a letter and a cell of bit vectors, a block of two runs, a border letter.
CELL_NS, BIT_LETTER_NS, BIT_CELL_NS, BLOCK_NS, BORDER_NS, CALL_NS = 8.0, 900.0, 0.2, 30_000.0, 4.0, 20_000.0


# An entry that a sweep reads, a strand and level of a braid merge, a vector step of a sweep.
PROBE_NS, STRAND_NS, STEP_NS = 60.0, 1100.0, 2_000.0
WORTH_NS = 50e6  # what the cheapest other route costs before the block method is looked at
PACKED = 50  # letters a byte of a quick compressor, below which no grammar is small enough


def block_ns(x: int, segments_a: int, segments_b: int, tables: int) -> float:
    """Price of the block method with braids: tables is how many symbols the first cut is made of times the different
    segments of the second one."""
    side = 3 * x + 1  # inputs of a block of segments of x to 2 x letters
    levels = math.log2(side + 1) + 1
    sweep = segments_a * segments_b * 2 * side * levels * PROBE_NS + (segments_a + segments_b) * levels * 35 * STEP_NS
    return CALL_NS + sweep + tables * 2 * side * levels * STRAND_NS


def route(pairs: DataFrame) -> DataFrame:
    """pairs (pair_id, a, b) -> route: trivial (an empty string, or equal ones), table (the built-in, for short
    strings), bits (bit vectors, for long ones), runs (runs against runs, where they are very long). The task that
    gets a long pair looks at its grammars too and may take the block method instead (distances.unit_distance)."""
    la, lb = F.length("a").cast("double"), F.length("b").cast("double")
    ra, rb = run_count(F.col("a")), run_count(F.col("b"))
    easy = (la == 0) | (lb == 0) | (F.col("a") == F.col("b"))
    table = CELL_NS * la * lb
    bits = CALL_NS + F.least(la, lb) * (BIT_LETTER_NS + BIT_CELL_NS * F.greatest(la, lb))
    runs = CALL_NS + BLOCK_NS * ra * rb + BORDER_NS * (ra * lb + rb * la)
    best = F.when(runs < F.least(table, bits), "runs").when(bits < table, "bits").otherwise("table")
    return pairs.withColumns({"route": F.when(easy, "trivial").otherwise(best), "price": F.least(table, bits, runs)})
