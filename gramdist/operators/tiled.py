"""One very large pair: both strings come in pieces, and the tiles of an antidiagonal of the grid run side by side.

A round joins each tile's two pieces with the bottom border of the tile above and the right border of the tile to its
left, both written by the round before, so a lost executor costs one tile. K + L - 1 rounds for K by L pieces. A task
holds two pieces and two borders; the driver holds a number a piece. Under unit costs a tile is swept in bit vectors in
the JVM, a border is a byte a letter, and neighbouring pieces are joined to SIDE letters first: fewer rounds and longer
vectors.
"""

from __future__ import annotations

from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import dp, jvm
from ..scoring import Scoring
from ..session import kept, parts, workers

SIDE = 1 << 18
BORDER = "i int, j int, side string, vals binary"


def _borders(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [()] * 4
    return pa.RecordBatch.from_arrays([pa.array(list(v), t) for v, t in zip(cols, (pa.int32(), pa.int32(), pa.string(), pa.binary()))], ["i", "j", "side", "vals"])


def _joined(df: DataFrame, rows: list[tuple]) -> tuple[DataFrame, list[tuple]]:
    """Neighbouring pieces (k, text) as one while they have SIDE letters or fewer; rows are (k, del, ins) in order."""
    of, sums = {}, []
    for k, d, i in rows:
        if sums and sums[-1][1] + d <= SIDE:
            sums[-1] = (sums[-1][0], sums[-1][1] + d, sums[-1][2] + i)
        else:
            sums.append((len(sums), d, i))
        of[k] = sums[-1][0]
    if len(sums) == len(rows):
        return df, rows
    n = F.create_map(*[F.lit(x) for kv in of.items() for x in kv])
    one = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("k", "text"))), lambda x: x["text"]), "")
    return kept(df.groupBy(n[F.col("k")].cast("long").alias("g")).agg(one.alias("text")).select(F.col("g").alias("k"), "text")), sums


def _unit(da: DataFrame, db: DataFrame, ca: list[tuple], cb: list[tuple]) -> float:
    """tiled_pieces under unit costs, from pieces and their lengths in order. Borders are differences between neighbours;
    a round's table has, for each tile, the value below right and the borders below it and to its right."""
    spark = da.sparkSession
    tile = jvm.unit_tile(spark)
    ends = accumulate(r[1] for r in ca)
    rows = spark.createDataFrame([(r[0], n, int(end)) for n, (r, end) in enumerate(zip(ca, ends))], "k long, i int, end long")
    cols = spark.createDataFrame([(r[0], n) for n, r in enumerate(cb)], "k long, j int")
    pieces_a = kept(da.join(rows, "k").select("i", "end", F.col("text").alias("a")))
    pieces_b = kept(db.join(cols, "k").select("j", F.col("text").alias("b")))
    done = spark.createDataFrame([], "i int, v binary")
    for wave in range(len(ca) + len(cb) - 1):
        now = pieces_a.join(pieces_b.select((F.lit(wave) - F.col("j")).alias("i"), "b"), "i")
        now = now.join(done.select((F.col("i") + 1).alias("i"), F.col("v").alias("above")), "i", "left").join(done.select("i", F.col("v").alias("before")), "i", "left")
        top = F.expr("coalesce(substring(above, 9, length(b)), cast(repeat(char(1), length(b)) AS binary))")
        left = F.expr("coalesce(substring(before, -length(a), length(a)), cast(repeat(char(1), length(a)) AS binary))")
        at = F.expr("coalesce(cast(conv(hex(substring(before, 1, 8)), 16, 10) AS bigint), end)")
        tiles = min(wave, len(ca) - 1) - max(0, wave - len(cb) + 1) + 1
        dealt = now.select("i", "a", "b", top.alias("top"), left.alias("left"), at.alias("at")).coalesce(1).repartition(tiles)  # one each
        done = kept(dealt.select("i", F.call_function(tile, "a", "b", "top", "left", "at").alias("v")))
    return float(int(done.select(F.hex(F.substring("v", 1, 8)).alias("v")).first()["v"], 16))


def tiled_pieces(a: DataFrame, b: DataFrame, scoring: Scoring | None = None) -> float:
    """The distance of two strings given as pieces (k, text), in order of k."""
    s = scoring or Scoring.unit()
    unit = s == Scoring.unit()
    workers(a.sparkSession)

    def costs(batches):
        for rb in batches:
            for k, t in zip(rb.column(0).to_pylist(), rb.column(1).to_pylist()):
                d, i = s.vectors(t, t)
                yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([float(d.sum())]), pa.array([float(i.sum())])], ["k", "del", "ins"])

    sides = []
    for df in (a, b):
        df = kept(df.where("text IS NOT NULL AND text != ''").select(F.col("k").cast("long").alias("k"), "text"))
        rows = sorted(map(tuple, df.mapInArrow(costs, "k long, del double, ins double").collect()))
        sides.append(_joined(df, rows) if unit else (df, rows))
    (da, ca), (db, cb) = sides
    if not ca or not cb:
        return (sum(r[1] for r in ca) + sum(r[2] for r in cb)) / s.denominator
    if unit:
        return _unit(da, db, ca, cb)
    place = [{r[0]: n for n, r in enumerate(c)} for c in (ca, cb)]
    start = [[0.0, *accumulate(r[1] for r in ca)], [0.0, *accumulate(r[2] for r in cb)]]

    def first(which: int):
        def run(batches):
            for rb in batches:
                rows = []
                for k, t in zip(rb.column(0).to_pylist(), rb.column(1).to_pylist()):
                    n = place[which][k]
                    step = s.vectors(t, t)[which]
                    v = np.r_[s.dtype(0), np.cumsum(step)] + s.dtype(start[which][n])
                    rows.append((n, 0, "left", v.tobytes()) if which == 0 else (0, n, "top", v.tobytes()))
                yield _borders(rows)

        return run

    def numbered(df: DataFrame, which: int, name: str, text: str) -> DataFrame:
        n = F.create_map(*[F.lit(x) for kv in place[which].items() for x in kv])
        return kept(df.select(n[F.col("k")].alias(name), F.col("text").alias(text)))

    pieces_a, pieces_b = numbered(da, 0, "i", "a"), numbered(db, 1, "j", "b")
    borders = kept(da.mapInArrow(first(0), BORDER).unionByName(db.mapInArrow(first(1), BORDER)))

    def sweep(batches):
        for rb in batches:
            for i, j, x, y, top, left in zip(*[rb.column(k).to_pylist() for k in range(6)]):
                row, left = np.frombuffer(top, s.dtype), np.frombuffer(left, s.dtype)
                c = dp.Letters(s, x, y)
                run = np.r_[s.dtype(0), np.cumsum(c.inserts)]
                right = [row[-1]]
                for k, (letter, d) in enumerate(zip(x, c.deletes), 1):
                    best = row + d
                    best[1:] = np.minimum(best[1:], row[:-1] + c.row(letter))
                    best[0] = left[k]
                    row = np.minimum.accumulate(best - run) + run
                    right.append(row[-1])
                yield _borders([(i + 1, j, "top", row.tobytes()), (i, j + 1, "left", np.array(right, s.dtype).tobytes())])

    for wave in range(len(ca) + len(cb) - 1):
        top = borders.where("side = 'top'").select("i", "j", F.col("vals").alias("top"))
        left = borders.where("side = 'left'").select("i", "j", F.col("vals").alias("left"))
        now = top.join(left, ["i", "j"]).where(F.col("i") + F.col("j") == wave).join(pieces_a, "i").join(pieces_b, "j")
        done = now.select("i", "j", "a", "b", "top", "left").repartition(parts(a.sparkSession), "i").mapInArrow(sweep, BORDER)
        borders = kept(done.unionByName(borders.where(F.col("i") + F.col("j") > wave)))
    last = borders.where(f"side = 'top' AND i = {len(ca)} AND j = {len(cb) - 1}").select(F.expr("substring(vals, length(vals) - 7, 8)").alias("v")).first()
    return np.frombuffer(last["v"], s.dtype)[0].item() / s.denominator


def tiled_distance(spark: SparkSession, a: str, b: str, tiles: int = 4, scoring: Scoring | None = None) -> float:
    """The same for two strings at hand, cut into even pieces."""
    cut = lambda t: spark.createDataFrame([(k, t[len(t) * k // tiles : len(t) * (k + 1) // tiles]) for k in range(tiles)], "k long, text string")
    return tiled_pieces(cut(a), cut(b), scoring)
