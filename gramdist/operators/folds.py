"""Boundary matrices as an ordered monoid: many pieces of a text against one template, merged pairwise in rounds."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import dist as D
from ..scoring import Scoring
from ..session import kept, workers

ROW = "k long, seq long, p int, payload binary"


def dist_fold(pieces: DataFrame, template: str, scoring: Scoring | None = None) -> DataFrame:
    """pieces (key, seq, text) -> (key, letters, distance): the pieces of a key in order of seq against the template.

    A round merges neighbours 2 m and 2 m + 1 of every key, so a task never holds more than two matrices of a key and
    the rounds are the logarithm of the largest number of pieces. Empty pieces are left out; a key of empty pieces
    alone gives no row.
    """
    s = scoring or Scoring.unit()
    workers(pieces.sparkSession)
    far, q = D.big(s), len(template)
    w = Window.partitionBy("key").orderBy("seq")
    rows = pieces.where("text IS NOT NULL AND text != ''").select(F.col("key").cast("long").alias("k"), (F.row_number().over(w) - 1).cast("long").alias("seq"), "text")

    def out(rows_: list[tuple]) -> pa.RecordBatch:
        k, seq, p, d = zip(*rows_) if rows_ else [()] * 4
        return pa.RecordBatch.from_arrays([pa.array(list(k), pa.int64()), pa.array(list(seq), pa.int64()), pa.array(list(p), pa.int32()), pa.array(list(d), pa.binary())], ["k", "seq", "p", "payload"])

    def single(batches):
        for b in batches:
            yield out([(k, n, len(t), D.by_increments(t, template, s).tobytes()) for k, n, t in zip(*[b.column(c).to_pylist() for c in range(3)])])

    def pair(t: pa.Table) -> pa.Table:
        rows_ = sorted(zip(*[t.column(c).to_pylist() for c in ("k", "seq", "p", "payload")]), key=lambda r: r[1])
        k, seq, p, d = rows_[0]
        if len(rows_) == 2:
            p2 = rows_[1][2]
            one, two = (np.frombuffer(x, s.dtype).reshape(m + q + 1, -1) for x, m in ((d, p), (rows_[1][3], p2)))
            d, p = D.merge_rows(one, two, p, p2, q, far).tobytes(), p + p2
        return pa.Table.from_batches([out([(k, seq // 2, p, d)])])

    cur = kept(rows.mapInArrow(single, ROW))
    while (cur.agg(F.max("seq")).first()[0] or 0) > 0:
        cur = kept(cur.groupBy("k", F.expr("seq div 2").alias("half")).applyInArrow(pair, ROW))

    def corner(batches):
        for b in batches:
            v = [np.frombuffer(d, s.dtype).reshape(p + q + 1, -1)[p, q].item() / s.denominator for p, d in zip(b.column(1).to_pylist(), b.column(2).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(b.column(1).to_pylist(), pa.int64()), pa.array(v, pa.float64())], ["key", "letters", "distance"])

    return cur.select("k", "p", "payload").mapInArrow(corner, "key long, letters long, distance double")
