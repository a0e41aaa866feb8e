"""The same semantics as relations: prefix tables, boundary matrices, propagation and merging as joins and minima.

These forms serve checks and SQL users; they make a row per cell or entry, so they are for short strings.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def piece(text: Column | str, start, end) -> Column:
    """Letters start..end of a text, from 0, end excluded."""
    c = F.col(text) if isinstance(text, str) else text
    return F.substring(c, start + 1, end - start)


def dp_table(pairs: DataFrame) -> DataFrame:
    """(pair_id, i, j, value): every prefix distance."""
    g = pairs.withColumn("i", F.explode(F.expr("sequence(0, length(a))"))).withColumn("j", F.explode(F.expr("sequence(0, length(b))")))
    return g.select("pair_id", "i", "j", F.levenshtein(F.expr("substring(a, 1, i)"), F.expr("substring(b, 1, j)")).cast("long").alias("value"))


def dp_distance_sql(pairs: DataFrame) -> DataFrame:
    """The table as nested folds over arrays, one row of it at a time: no Python, no rows per cell."""
    letters = "split(b, '')"
    start = "sequence(0, length(b))"
    step = (
        "(row, c) -> aggregate("
        f"sequence(1, length(b)), array(row[0] + 1), (acc, j) -> concat(acc, array(least(row[j] + 1, acc[j - 1] + 1, row[j - 1] + CASE WHEN {letters}[j - 1] = c THEN 0 ELSE 1 END))))"
    )
    value = f"element_at(aggregate(split(a, ''), {start}, {step}), -1)"
    return pairs.select("pair_id", F.when((F.length("a") == 0) | (F.length("b") == 0), F.length("a") + F.length("b")).otherwise(F.expr(value)).cast("long").alias("distance"))


def vertices(side: str) -> str:
    """Row and column of input or output vertex number k of a block of p rows and q columns."""
    if side == "in":
        return "struct(greatest(p - k, 0) AS r, greatest(k - p, 0) AS c)"
    return "struct(p - greatest(k - q, 0) AS r, least(k, q) AS c)"


def dist_rows(pairs: DataFrame) -> DataFrame:
    """(pair_id, i, j, w): the boundary matrix as an edge list; pairs without a path have no row."""
    d = pairs.withColumns({"p": F.length("a"), "q": F.length("b")})
    d = d.withColumn("i", F.explode(F.expr("sequence(0, p + q)"))).withColumn("j", F.explode(F.expr("sequence(0, p + q)"))).where("j <= q + i AND i <= p + j")
    d = d.withColumns({"u": F.expr(vertices("in").replace("k", "i")), "v": F.expr(vertices("out").replace("k", "j"))})
    w = F.levenshtein(F.expr("substring(a, u.r + 1, v.r - u.r)"), F.expr("substring(b, u.c + 1, v.c - u.c)"))
    return d.select("pair_id", "i", "j", w.cast("long").alias("w"))


def propagate_rows(inputs: DataFrame, table: DataFrame, keys: tuple[str, ...] = ("pair_id",)) -> DataFrame:
    """inputs (keys, i, v) through a matrix (keys, i, j, w): (keys, j, v), the minimum over i."""
    return inputs.join(table, [*keys, "i"]).groupBy(*keys, "j").agg(F.min(F.col("v") + F.col("w")).alias("v"))


def merge_rows(first: DataFrame, second: DataFrame, p: int, q1: int, keys: tuple[str, ...] = ("pair_id",)) -> DataFrame:
    """Edge lists of blocks with the same p rows, side by side (first has q1 columns): the joined block's edge list.
    Paths cross at the first block's outputs q1.., which are the second's inputs 0..p."""
    across = first.where(F.col("j") >= q1).select(*keys, "i", (F.col("j") - q1).alias("k"), F.col("w").alias("w1"))
    second_in = second.where(F.col("i") <= p).select(*keys, F.col("i").alias("k"), (F.col("j") + q1).alias("j"), F.col("w").alias("w2"))
    cross = across.join(second_in, [*keys, "k"]).select(*keys, "i", "j", (F.col("w1") + F.col("w2")).alias("w"))
    stay = first.where(F.col("j") <= q1).select(*keys, "i", "j", "w")
    later = second.where(F.col("i") > p).select(*keys, (F.col("i") + q1).alias("i"), (F.col("j") + q1).alias("j"), "w")
    return cross.unionByName(stay).unionByName(later).groupBy(*keys, "i", "j").agg(F.min("w").alias("w"))


def grid_edges(pairs: DataFrame) -> DataFrame:
    """The grid as a weighted graph with unit costs: (pair_id, src, dst, w); a vertex is i * (length of b + 1) + j."""
    g = pairs.withColumn("n", F.length("b") + 1).withColumn("i", F.explode(F.expr("sequence(0, length(a))"))).withColumn("j", F.explode(F.expr("sequence(0, length(b))")))
    same = "CASE WHEN substring(a, i, 1) = substring(b, j, 1) THEN 0 ELSE 1 END"
    into = F.expr(f"filter(array(CASE WHEN i > 0 THEN struct((i - 1) * n + j AS src, 1 AS w) END, CASE WHEN j > 0 THEN struct(i * n + j - 1 AS src, 1 AS w) END, CASE WHEN i > 0 AND j > 0 THEN struct((i - 1) * n + j - 1 AS src, {same} AS w) END), e -> e IS NOT NULL)")
    return g.select("pair_id", F.expr("i * n + j").alias("dst"), F.explode(into).alias("e")).select("pair_id", "e.src", "dst", "e.w")


def lightest_path(edges: DataFrame) -> DataFrame:
    """(pair_id, distance): weight of the lightest path from vertex 0 to the last vertex, by rounds of relaxation.
    Unit weights bound the rounds by the number of vertices on a path; a round is a join and a minimum."""
    from ..session import kept

    edges = kept(edges)
    end = edges.groupBy("pair_id").agg(F.max("dst").alias("last"))
    best = kept(edges.select("pair_id").distinct().select("pair_id", F.lit(0).alias("v"), F.lit(0).cast("long").alias("d")))
    while True:
        new = best.join(edges.withColumnRenamed("src", "v"), ["pair_id", "v"]).select("pair_id", F.col("dst").alias("v"), (F.col("d") + F.col("w")).alias("d"))
        nxt = kept(best.unionByName(new).groupBy("pair_id", "v").agg(F.min("d").alias("d")))
        same = nxt.join(best, ["pair_id", "v", "d"], "left_anti").isEmpty()
        best = nxt
        if same:
            break
    return best.join(end, (best.pair_id == end.pair_id) & (best.v == end["last"])).select(best.pair_id, F.col("d").alias("distance"))
