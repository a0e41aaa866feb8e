"""Scoring functions: the costs of deleting, inserting and replacing letters."""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CLASSES = ("unit", "rational", "arbitrary")


@dataclass(frozen=True)
class Scoring:
    """Costs are numbers over one denominator: whole numerators for rational scoring, floats for arbitrary scoring.

    Letters without an own entry cost the defaults. Equal letters cost 0 unless free_match is off.
    """

    delete: float = 1
    insert: float = 1
    replace: float = 1
    denominator: int = 1
    kind: str = "unit"
    free_match: bool = True
    deletes: dict = field(default_factory=dict)
    inserts: dict = field(default_factory=dict)
    replaces: dict = field(default_factory=dict)

    @staticmethod
    def unit() -> Scoring:
        return Scoring()

    @staticmethod
    def indel() -> Scoring:
        """Replacing costs a deletion and an insertion, so the distance is both lengths less twice the longest common subsequence."""
        return Scoring(1, 1, 2, 1, "rational")

    @staticmethod
    def rational(delete, insert, replace) -> Scoring:
        parts = [Fraction(x).limit_denominator(10**6) for x in (delete, insert, replace)]
        den = int(np.lcm.reduce([p.denominator for p in parts]))
        d, i, r = (int(p * den) for p in parts)
        return Scoring(d, i, r, den, "rational")

    @staticmethod
    def matrix(alphabet: str, costs, delete, insert, kind: str = "arbitrary") -> Scoring:
        """costs[a][b] replaces letter a of the alphabet by letter b."""
        table = {(x, y): costs[i][j] for i, x in enumerate(alphabet) for j, y in enumerate(alphabet) if i != j}
        return Scoring(delete, insert, max(table.values(), default=delete + insert), 1, kind, True, {}, {}, table)

    @staticmethod
    def from_table(df: DataFrame, delete, insert, replace, kind: str = "arbitrary") -> Scoring:
        """Rows (op, a, b, cost); op is del, ins or sub. A cost table has a row for each pair of letters, at most."""
        rows = df.select("op", "a", "b", "cost").toLocalIterator()
        d, i, r = {}, {}, {}
        for op, a, b, c in rows:
            cost = int(c) if float(c).is_integer() else float(c)
            if op == "del":
                d[a] = cost
            elif op == "ins":
                i[b] = cost
            else:
                r[a, b] = cost
        return Scoring(delete, insert, replace, 1, kind, True, d, i, r)

    @cached_property
    def uniform(self) -> bool:
        return not (self.deletes or self.inserts or self.replaces)

    @property
    def key(self) -> tuple:
        return (self.delete, self.insert, self.replace, self.denominator, self.free_match, *[tuple(sorted(x.items())) for x in (self.deletes, self.inserts, self.replaces)])

    @cached_property
    def dtype(self):
        whole = all(isinstance(x, (int, np.integer)) for x in (self.delete, self.insert, self.replace, *self.deletes.values(), *self.inserts.values(), *self.replaces.values()))
        return np.int64 if whole else np.float64

    @cached_property
    def largest(self):
        return max([self.delete, self.insert, self.replace, *self.deletes.values(), *self.inserts.values(), *self.replaces.values()])

    def del_cost(self, a: str):
        return self.deletes.get(a, self.delete)

    def ins_cost(self, b: str):
        return self.inserts.get(b, self.insert)

    def sub_cost(self, a: str, b: str):
        return 0 if a == b and self.free_match else self.replaces.get((a, b), self.replace)

    def vectors(self, a: str, b: str) -> tuple[np.ndarray, np.ndarray]:
        """Deletion costs along a, insertion costs along b."""
        t = self.dtype
        return np.array([self.del_cost(x) for x in a], t), np.array([self.ins_cost(x) for x in b], t)

    def row(self, a: str, b: str) -> np.ndarray:
        """Replacement costs of the letter a against every letter of b."""
        return np.array([self.sub_cost(a, y) for y in b], self.dtype)


VOWELS = "aeiouAEIOU"


def letter_classes(scale: float = 1) -> Scoring:
    """Vowel for vowel 1, consonant for consonant 2, across 3; gaps 2; times scale."""
    letters = "abcdefghijklmnopqrstuvwxyz"
    letters += letters.upper()
    kind = lambda x: x in VOWELS
    table = {}
    for x in letters:
        for y in letters:
            if x != y:
                table[x, y] = scale * (3 if kind(x) != kind(y) else 1 if kind(x) else 2)
    return Scoring(2 * scale, 2 * scale, 2 * scale, 1, "arbitrary", True, {}, {}, table)


def cost_rows(spark: SparkSession, scoring: Scoring, alphabet: str) -> DataFrame:
    """The cost table of an alphabet as rows (op, a, b, cost)."""
    rows = [("del", x, None, float(scoring.del_cost(x))) for x in alphabet] + [("ins", None, x, float(scoring.ins_cost(x))) for x in alphabet]
    rows += [("sub", x, y, float(scoring.sub_cost(x, y))) for x in alphabet for y in alphabet]
    return spark.createDataFrame(rows, "op string, a string, b string, cost double")


def check_metric(costs: DataFrame) -> DataFrame:
    """Violations of the metric axioms in a cost table, a row each: (axiom, a, b, c, excess).

    The triangle test joins replacements on their shared letter, so it is of alphabet size cubed, not of data size.
    """
    sub = costs.where("op = 'sub'").select("a", "b", "cost")
    gaps = costs.where("op = 'del'").select("a", F.col("cost").alias("d")).join(costs.where("op = 'ins'").select(F.col("b").alias("a"), F.col("cost").alias("i")), "a")
    none = F.lit(None).cast("string")
    out = costs.where("cost < 0").select(F.lit("nonnegative").alias("axiom"), "a", "b", none.alias("c"), (-F.col("cost")).alias("excess"))
    out = out.unionByName(sub.where("(a = b AND cost != 0) OR (a != b AND cost <= 0)").select(F.lit("identity").alias("axiom"), "a", "b", none.alias("c"), F.abs("cost").alias("excess")))
    back = sub.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("cost").alias("back"))
    out = out.unionByName(sub.join(back, ["a", "b"]).where("a < b AND cost != back").select(F.lit("symmetry").alias("axiom"), "a", "b", none.alias("c"), F.abs(F.col("cost") - F.col("back")).alias("excess")))
    out = out.unionByName(gaps.where("d != i").select(F.lit("symmetry").alias("axiom"), "a", none.alias("b"), none.alias("c"), F.abs(F.col("d") - F.col("i")).alias("excess")))
    two = sub.select(F.col("b").alias("m"), "a", F.col("cost").alias("c1")).join(sub.select(F.col("a").alias("m"), "b", F.col("cost").alias("c2")), "m")
    tri = two.join(sub, ["a", "b"]).where("cost > c1 + c2 + 1e-9").select(F.lit("triangle").alias("axiom"), "a", "b", F.col("m").alias("c"), (F.col("cost") - F.col("c1") - F.col("c2")).alias("excess"))
    return out.unionByName(tri)
