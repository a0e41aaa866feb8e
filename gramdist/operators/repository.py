"""A repository of boundary matrices shared by all pairs of a workload, kept as a table between jobs.

Keys are the two texts of a symbol pair, so equal segments of different strings, grammars and pairs meet in one row.
The plan is closed downwards level by level, known keys are dropped by an anti join, and each level's tables are
merged from the levels below by two joins and an Arrow kernel. A level is written once and never rewritten. Payloads are
dense matrices of the scoring's numbers, so a table's bytes grow with the square of its segments: x bounds them.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import cuts
from ..functions import dist as D
from ..functions import grammar as G
from ..model import DIST
from ..scoring import Scoring
from ..session import kept, workers


def symbols(strings: DataFrame, x: int, codec: str = "lz78") -> DataFrame:
    """Distinct symbols of each string's cut with what they are made of: (string_id, text, left, right, segment)."""
    workers(strings.sparkSession)
    names = ["string_id", "text", "left", "right", "segment"]

    def run(batches):
        for b in batches:
            out = []
            for ident, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                c = cuts.grammar_cut(G.compress(text, codec), x)
                own, todo, seen = set(c.segments), list(set(c.segments)), {}
                while todo:
                    v = todo.pop()
                    if v in seen:
                        continue
                    seen[v] = c.text(v)
                    if c.lhs[v] >= 0:
                        todo += [c.lhs[v], c.rhs[v]]
                for v, t in seen.items():
                    part = c.lhs[v] >= 0
                    out.append((ident, t, seen[c.lhs[v]] if part else None, seen[c.rhs[v]] if part else None, v in own))
            cols = list(zip(*out)) if out else [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(cols, (pa.int64(), pa.string(), pa.string(), pa.string(), pa.bool_()))], names)

    rows = strings.where("text IS NOT NULL AND text != ''").select(F.col("string_id").cast("long").alias("string_id"), "text")
    return rows.mapInArrow(run, "string_id long, text string, left string, right string, segment boolean")


def plan(pairs: DataFrame, syms: DataFrame) -> DataFrame:
    """Distinct (a, b) that the pairs' blocks need: every segment of one side with every segment of the other, per
    pair of strings, by an equi-join on the pair; distinct over the whole workload."""
    seg = syms.where("segment").select("string_id", "text").distinct()
    a = seg.select(F.col("string_id").alias("a_id"), F.col("text").alias("a"))
    b = seg.select(F.col("string_id").alias("b_id"), F.col("text").alias("b"))
    return pairs.join(a, "a_id").join(b, "b_id").select("a", "b").distinct()


def together(tables: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, tables)


def close(needed: DataFrame, syms: DataFrame) -> DataFrame:
    """The keys that tables are merged from, all the way down: split the longer side, one merge a key."""
    # one way to split a text is enough for all grammars that hold it
    split = kept(syms.where("left IS NOT NULL").groupBy("text").agg(F.min(F.struct("left", "right")).alias("s")).select("text", "s.left", "s.right"))
    levels: list[DataFrame] = []
    new = kept(needed.select("a", "b").distinct())
    while not new.isEmpty():
        rows = F.length("a") >= F.length("b")
        by_a = new.where(rows & (F.length("a") > 1)).join(split.withColumnRenamed("text", "a"), "a").select("a", "b", F.col("left").alias("a1"), F.col("b").alias("b1"), F.col("right").alias("a2"), F.col("b").alias("b2"))
        by_b = new.where(~rows).join(split.withColumnRenamed("text", "b"), "b").select("a", "b", F.col("a").alias("a1"), F.col("left").alias("b1"), F.col("a").alias("a2"), F.col("right").alias("b2"))
        none = F.lit(None).cast("string")
        leaf = new.where("length(a) = 1 AND length(b) = 1").select("a", "b", none.alias("a1"), none.alias("b1"), none.alias("a2"), none.alias("b2"))
        level = kept(by_a.unionByName(by_b).unionByName(leaf))
        levels.append(level)
        below = level.where("a1 IS NOT NULL")
        nxt = below.select(F.col("a1").alias("a"), F.col("b1").alias("b")).unionByName(below.select(F.col("a2").alias("a"), F.col("b2").alias("b"))).distinct()
        new = kept(nxt.join(together(levels).select("a", "b"), ["a", "b"], "left_anti"))
    return together(levels) if levels else needed.sparkSession.createDataFrame([], "a string, b string, a1 string, b1 string, a2 string, b2 string")


def build(closed: DataFrame, scoring: Scoring | None = None, known: DataFrame | None = None) -> DataFrame:
    """Tables of all keys, in order of their letters: a table is merged from two of fewer letters. known is a
    repository of an earlier job; its keys are not made again."""
    s = scoring or Scoring.unit()
    spark = closed.sparkSession
    workers(spark)
    todo = closed.withColumn("letters", F.length("a") + F.length("b"))
    if known is not None:
        have = known.select(F.col("a_text").alias("a"), F.col("b_text").alias("b"))
        todo = todo.join(have, ["a", "b"], "left_anti")
    todo = kept(todo)
    levels = [] if known is None else [known]

    def leaves(batches):
        for b in batches:
            rows = [(x, y, 1, 1, D.leaf(x, y, s).tobytes()) for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist())]
            yield _pack(rows)

    def merges(batches):
        far = D.big(s)
        for b in batches:
            rows = []
            for x, y, x1, y1, one, two in zip(*[b.column(k).to_pylist() for k in range(6)]):
                p, q, p1, q1 = len(x), len(y), len(x1), len(y1)
                d1 = np.frombuffer(one, s.dtype).reshape(p1 + q1 + 1, -1)
                if q1 == q:
                    d2 = np.frombuffer(two, s.dtype).reshape(p - p1 + q + 1, -1)
                    d = D.merge_rows(d1, d2, p1, p - p1, q, far)
                else:
                    d2 = np.frombuffer(two, s.dtype).reshape(p + q - q1 + 1, -1)
                    d = D.merge_columns(d1, d2, p, q1, q - q1, far)
                rows.append((x, y, p, q, d.tobytes()))
            yield _pack(rows)

    made = kept(todo.where("a1 IS NULL").select("a", "b").mapInArrow(leaves, DIST))
    levels.append(made)
    todo = kept(todo.where("a1 IS NOT NULL"))
    while not todo.isEmpty():
        done = together(levels)
        one = done.select(F.col("a_text").alias("a1"), F.col("b_text").alias("b1"), F.col("payload").alias("one"))
        two = done.select(F.col("a_text").alias("a2"), F.col("b_text").alias("b2"), F.col("payload").alias("two"))
        ready = todo.join(one, ["a1", "b1"]).join(two, ["a2", "b2"])
        made = kept(ready.select("a", "b", "a1", "b1", "one", "two").mapInArrow(merges, DIST))
        if made.isEmpty():
            raise ValueError("a key's parts are missing from the plan")
        todo = kept(todo.join(made.select(F.col("a_text").alias("a"), F.col("b_text").alias("b")), ["a", "b"], "left_anti"))
        levels.append(made)
    return together(levels)


def uniform(pairs: DataFrame, strings: DataFrame, x: int, scoring: Scoring | None = None) -> DataFrame:
    """The repository of the equal-pieces cut: every distinct pair of pieces that a pair of strings needs, built
    directly, without merging."""
    s = scoring or Scoring.unit()
    workers(pairs.sparkSession)
    cut = strings.where("text IS NOT NULL AND text != ''").select("string_id", F.explode(F.expr(f"array_distinct(transform(sequence(0, cast((length(text) - 1) / {x} AS int)), k -> substring(text, k * {x} + 1, {x})))")).alias("text"))
    a = cut.select(F.col("string_id").alias("a_id"), F.col("text").alias("a"))
    b = cut.select(F.col("string_id").alias("b_id"), F.col("text").alias("b"))
    need = pairs.join(a, "a_id").join(b, "b_id").select("a", "b").distinct()

    def run(batches):
        for rb in batches:
            yield _pack([(u, v, len(u), len(v), D.by_increments(u, v, s).tobytes()) for u, v in zip(rb.column(0).to_pylist(), rb.column(1).to_pylist())])

    return need.mapInArrow(run, DIST)


def corners(repo: DataFrame, scoring: Scoring | None = None) -> DataFrame:
    """(a_text, b_text, distance): each table's top-left to bottom-right entry, the distance of its two texts."""
    s = scoring or Scoring.unit()

    def run(batches):
        for b in batches:
            d = [np.frombuffer(x, s.dtype).reshape(p + q + 1, -1)[p, q].item() for p, q, x in zip(*[b.column(c).to_pylist() for c in (2, 3, 4)])]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([float(v) / s.denominator for v in d])], ["a_text", "b_text", "distance"])

    return repo.select("a_text", "b_text", "p", "q", "payload").mapInArrow(run, "a_text string, b_text string, distance double")


def _pack(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [()] * 5
    types = (pa.string(), pa.string(), pa.int32(), pa.int32(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types)], ["a_text", "b_text", "p", "q", "payload"])


def write_repository(repo: DataFrame, path: str) -> None:
    """Append keys that the store lacks; running it twice adds nothing."""
    spark = repo.sparkSession
    try:
        have = spark.read.schema(DIST).parquet(path).select("a_text", "b_text")
        repo = kept(repo.join(have, ["a_text", "b_text"], "left_anti"))
    except Exception as e:  # noqa: BLE001
        if "PATH_NOT_FOUND" not in str(e):
            raise
    repo.write.mode("append").parquet(path)


def read_repository(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(DIST).parquet(path)


def shared_distance(pairs: DataFrame, strings: DataFrame, x: int, scoring: Scoring | None = None, codec: str = "lz78", known: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(distances, repository): build what the whole workload needs once, then sweep each pair with its tables.

    A pair's tables come to its task as one list; it is of distinct symbol pairs, not of blocks."""
    s = scoring or Scoring.unit()
    syms = kept(symbols(strings, x, codec))
    need = kept(plan(pairs, syms))
    repo = build(close(need, syms), s, known)
    seg = syms.where("segment").select("string_id", "text").distinct()
    a = seg.select(F.col("string_id").alias("a_id"), F.col("text").alias("a_text"))
    b = seg.select(F.col("string_id").alias("b_id"), F.col("text").alias("b_text"))
    per = pairs.join(a, "a_id").join(b, "b_id").join(repo.select("a_text", "b_text", "payload"), ["a_text", "b_text"])
    per = per.groupBy("pair_id", "a_id", "b_id").agg(F.collect_list(F.struct("a_text", "b_text", "payload")).alias("tables"))
    texts = strings.select("string_id", "text")
    per = per.join(texts.withColumnsRenamed({"string_id": "a_id", "text": "a"}), "a_id").join(texts.withColumnsRenamed({"string_id": "b_id", "text": "b"}), "b_id")

    def sweep(batches):
        from ..functions import blocks as B

        for rb in batches:
            ids, values = [], []
            for ident, x_text, y_text, tables in zip(rb.column(0).to_pylist(), rb.column(1).to_pylist(), rb.column(2).to_pylist(), rb.column(3).to_pylist()):
                r = B.Repository(s)
                for t in tables:
                    n = len(t["a_text"]) + len(t["b_text"]) + 1
                    r.tables[t["a_text"], t["b_text"]] = np.frombuffer(t["payload"], s.dtype).reshape(n, n)
                ca, cb = (cuts.grammar_cut(G.compress(v, codec), x) for v in (x_text, y_text))
                ids.append(ident)
                values.append(B.sweep(ca, cb, r) / s.denominator)
            yield pa.RecordBatch.from_arrays([pa.array(ids, rb.schema.field(0).type), pa.array(values, pa.float64())], ["pair_id", "distance"])

    kind = pairs.schema["pair_id"].dataType.simpleString()
    return per.select("pair_id", "a", "b", "tables").mapInArrow(sweep, f"pair_id {kind}, distance double"), repo
