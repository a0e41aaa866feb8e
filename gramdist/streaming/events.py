"""Structured Streaming: event strings by window and session, and running distances to a template."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import dist as D
from ..functions import dp
from ..model import EVENT
from ..scoring import Scoring
from ..session import scratch, workers


def read_events(spark: SparkSession, path: str, files: int = 1, watermark: str = "10 minutes") -> DataFrame:
    """A stream of event rows from parquet files; an event id is counted once within the watermark. path may be a
    folder or one file: the pattern in its last letter lets the source take either."""
    path = f"{path[:-1]}[{path[-1]}]"
    df = spark.readStream.schema(EVENT).option("maxFilesPerTrigger", files).parquet(path)
    df = df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    return df.dropDuplicatesWithinWatermark(["event_id"])


def with_letter(events: DataFrame) -> DataFrame:
    return events.withColumn("letter", F.upper(F.substring("event_type", 1, 1)))


def joined_letters() -> F.Column:
    return F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "letter"))), lambda x: x["letter"]), "")


def window_strings(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(user_id, start, text): the events of each user and window in order, tumbling or sliding."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    g = with_letter(events).groupBy("user_id", w.alias("w")).agg(joined_letters().alias("text"))
    return g.select("user_id", F.col("w.start").alias("start"), "text")


def session_strings(events: DataFrame, gap: str) -> DataFrame:
    """(user_id, start, text): the events of each user without a pause of gap or more."""
    g = with_letter(events).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(joined_letters().alias("text"))
    return g.select("user_id", F.col("w.start").alias("start"), "text")


def against(strings: DataFrame, templates: DataFrame) -> DataFrame:
    """Stream strings against reference strings (name, template): a static side small enough to be sent to all."""
    return strings.crossJoin(F.broadcast(templates)).withColumn("distance", F.levenshtein("text", "template").cast("long"))


def running_distance(events: DataFrame, template: str, scoring: Scoring | None = None) -> DataFrame:
    """(user_id, events, distance): after each trigger, the distance of all a user's events so far to the template.

    State is the last row of the table, one number per template letter: a new event is one more row. Events of a
    trigger are put in order; one that comes after later events were folded in counts at its arrival.
    """
    s = scoring or Scoring.unit()
    workers(events.sparkSession)

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        n, row = state.get if state.exists else (0, None)
        c = dp.Letters(s, "", template)
        run = np.r_[s.dtype(0), np.cumsum(c.inserts)]
        row = run.copy() if row is None else np.array(row, s.dtype)
        for x in rows["letter"]:
            best = row + s.dtype(s.del_cost(x))
            best[1:] = np.minimum(best[1:], row[:-1] + c.row(x))
            row = np.minimum.accumulate(best - run) + run
            n += 1
        state.update((n, [float(v) for v in row]))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "distance": [float(row[-1]) / s.denominator]})

    return with_letter(events).groupBy("user_id").applyInPandasWithState(step, "user_id long, events long, distance double", "n long, row array<double>", "update", GroupStateTimeout.NoTimeout)


def fold_pieces(pieces: list[str], template: str, scoring: Scoring | None = None) -> np.ndarray:
    """Boundary matrix of the joined pieces against the template, merged pairwise: pieces are an ordered monoid, so a
    window that moves drops old pieces and adds new ones without reading the letters between again."""
    s = scoring or Scoring.unit()
    far, q = D.big(s), len(template)
    parts = [(len(p), D.by_increments(p, template, s)) for p in pieces if p]
    while len(parts) > 1:
        parts = [(parts[k][0] + parts[k + 1][0], D.merge_rows(parts[k][1], parts[k + 1][1], parts[k][0], parts[k + 1][0], q, far)) if k + 1 < len(parts) else parts[k] for k in range(0, len(parts), 2)]
    return parts[0][1]


def run_once(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now and give its output rows; in update mode the last row of each key."""
    spark = stream.sparkSession
    out, mark = scratch(spark), scratch(spark)

    def put(df: DataFrame, epoch: int) -> None:
        df.withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{out}/epoch={epoch:08d}-part")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", mark).trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    schema = T.StructType([*stream.schema.fields, T.StructField("epoch", T.IntegerType())])
    try:
        return spark.read.schema(schema).parquet(f"{out}/*-part")
    except Exception as e:  # noqa: BLE001
        if "PATH_NOT_FOUND" not in str(e):
            raise
        return spark.createDataFrame([], schema)
