"""Joins by distance, nearest strings, contained passages, and classes of near copies."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import blocks as B
from ..session import kept, workers


def similarity_join(strings: DataFrame, k: int) -> DataFrame:
    """Pairs of distinct texts at unit distance k or less: (a, b, distance), a < b.

    A text cut into k + 1 even pieces shares one piece whole with any text within k edits, moved by at most k places,
    and their lengths differ by at most k. So each text is sent under its pieces for its own length, and under the
    windows that such pieces of lengths near its own may have; only texts that meet are compared, with an early stop.
    Equal texts are merged first; candidates are distinct before they are verified.
    """
    texts = kept(strings.select("text").where("text IS NOT NULL").distinct().withColumn("n", F.length("text")))
    cut = f"transform(sequence(0, {k}), i -> struct(i AS piece, cast(floor(n * i / {k + 1}) AS int) AS s, cast(floor(n * (i + 1) / {k + 1}) AS int) AS e))"
    held = texts.select("text", "n", F.explode(F.expr(cut)).alias("p")).select(F.col("text").alias("b"), F.col("n").alias("m"), "p.piece", F.expr("substring(text, p.s + 1, p.e - p.s)").alias("key"))
    # lengths m up to n - k .. n: the longer text looks for the shorter one's pieces
    probe = texts.withColumn("m", F.explode(F.expr(f"sequence(greatest(n - {k}, 0), n)"))).select("text", "n", "m", F.explode(F.expr(cut.replace("n * ", "m * "))).alias("p"))
    probe = probe.withColumn("at", F.explode(F.expr(f"sequence(greatest(p.s - {k}, 0), least(p.s + {k}, n - (p.e - p.s)))")))
    probe = probe.where(f"p.s - {k} <= n - (p.e - p.s)").select(F.col("text").alias("a"), "m", "p.piece", F.expr("substring(text, at + 1, p.e - p.s)").alias("key")).distinct()
    met = probe.join(held, ["m", "piece", "key"]).where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    return met.withColumn("distance", F.levenshtein("a", "b", k)).where("distance >= 0").withColumn("distance", F.col("distance").cast("long"))


def shared_minima(strings: DataFrame, hashes: int = 3, width: int = 5) -> DataFrame:
    """Pairs (a_id, b_id) of likely near copies, from whole texts: under each of several hashes a text goes by the least
    hash of its shingles of `width` blank-separated words, and the texts of one least hash are linked in a chain, by id.
    Two texts with Jaccard j go together under one hash with chance j, so 0.8 is missed 8 times in 1,000 by three.

    Hashes are slices of one MD5, the same in any SQL engine. Only ids are sorted; a chain has one link less than rows,
    however many share a hash. Texts of fewer words are one shingle."""
    words = F.split(F.trim(F.regexp_replace("text", r"\s+", " ")), " ")
    own = strings.where("text IS NOT NULL").select("string_id", words.alias("w"))
    marks = own.select("string_id", F.expr(f"transform(sequence(1, greatest(size(w) - {width - 1}, 1)), k -> md5(array_join(slice(w, k, {width}), ' ')))").alias("m"))
    least = [F.struct(F.lit(k).alias("k"), F.expr(f"array_min(transform(m, x -> substring(x, {1 + 10 * k}, 10)))").alias("key")) for k in range(hashes)]
    keyed = marks.select("string_id", F.explode(F.array(*least)).alias("h")).select("string_id", "h.k", "h.key")
    w = Window.partitionBy("k", "key").orderBy("string_id")
    return keyed.select(F.col("string_id").alias("a_id"), F.lead("string_id").over(w).alias("b_id")).where("b_id IS NOT NULL").distinct()


def nearest(queries: DataFrame, strings: DataFrame, top: int) -> DataFrame:
    """Each query's nearest strings by unit distance: (query_id, string_id, distance, rank), ties by id. A stated set
    of queries meets all strings; every pair's distance goes to the query's window, whose rank filter Spark applies
    before the shuffle too, so a task sends at most `top` rows a query. The queries are sent to all tasks."""
    q = F.struct(F.col("string_id").alias("query_id"), F.col("text").alias("q"))
    blocks = queries.groupBy(F.pmod(F.xxhash64("string_id"), F.lit(8)).alias("block")).agg(F.collect_list(q).alias("qs"))
    rows = strings.select("string_id", "text").crossJoin(F.broadcast(blocks)).select("string_id", "text", F.explode("qs").alias("x"))
    d = rows.where("x.query_id != string_id").select("x.query_id", "string_id", F.levenshtein("x.q", "text").cast("long").alias("distance"))
    w = Window.partitionBy("query_id").orderBy("distance", "string_id")
    return d.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= top)


MOST_KEYS = 500_000  # pieces of patterns that are sent to all tasks: 20 letters each, some 50 MB


def contained(patterns: DataFrame, texts: DataFrame, width: int = 20) -> DataFrame:
    """Least unit distance of a pattern to any window of a text, for pairs that share `width` letters in a row at a
    whole multiple of width in the pattern: (pattern_id, string_id, distance).

    Texts are probed at every place, patterns (the small side) at every width-th; a pattern that lies in a text with
    fewer than length / width edits shares one of those pieces, so it is found. Up to MOST_KEYS pieces are sent to
    all tasks; more of them meet the texts' pieces by a join on their hash.
    """
    workers(texts.sparkSession)
    pieces = patterns.select(F.col("string_id").alias("pattern_id"), F.explode(F.expr(f"transform(sequence(0, greatest(cast(length(text) / {width} AS int) - 1, 0)), k -> substring(text, k * {width} + 1, {width}))")).alias("piece"))
    pieces = kept(pieces.where(F.length("piece") == width).distinct())
    found = _probed(pieces, texts, width) if pieces.count() <= MOST_KEYS else _joined(pieces, texts, width)
    met = found.join(patterns.select(F.col("string_id").alias("pattern_id"), F.col("text").alias("p")), "pattern_id").join(texts.select("string_id", F.col("text").alias("t")), "string_id")

    def run(batches):
        for b in batches:
            d = [B.best_window(p, t) for p, t in zip(b.column(2).to_pylist(), b.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(d, pa.int64())], ["pattern_id", "string_id", "distance"])

    return met.select("pattern_id", "string_id", "p", "t").mapInArrow(run, "pattern_id long, string_id long, distance long")


def _probed(pieces: DataFrame, texts: DataFrame, width: int) -> DataFrame:
    held: dict[str, list[int]] = {}
    for r in pieces.toLocalIterator():
        held.setdefault(r.piece, []).append(r.pattern_id)
    shared = texts.sparkSession.sparkContext.broadcast(held)

    def run(batches):
        known = shared.value
        for b in batches:
            a, c = [], []
            for ident, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                hits = {p for i in range(len(t or "") - width + 1) for p in known.get(t[i : i + width], ())}
                a += sorted(hits)
                c += [ident] * len(hits)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(c, pa.int64())], ["pattern_id", "string_id"])

    return texts.select("string_id", "text").mapInArrow(run, "pattern_id long, string_id long")


def _joined(pieces: DataFrame, texts: DataFrame, width: int) -> DataFrame:
    def run(batches):
        for b in batches:
            for ident, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                own = sorted({t[i : i + width] for i in range(len(t or "") - width + 1)})
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.string()), pa.array([ident] * len(own), pa.int64())], ["piece", "string_id"])

    grams = texts.select("string_id", "text").mapInArrow(run, "piece string, string_id long")
    return pieces.join(grams, "piece").select("pattern_id", "string_id").distinct()


def classes(edges: DataFrame) -> DataFrame:
    """(v, label) of all vertices of edges (a, b): the smallest vertex of each connected component.

    Every round takes the least label among neighbours and then the label's own label, so the rounds grow with the
    logarithm of a component's diameter; each round is written before the next."""
    both = kept(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = kept(both.select(F.col("a").alias("v")).distinct().withColumn("label", F.col("v")))
    while True:
        near = both.join(labels.withColumnRenamed("v", "b"), "b").groupBy(F.col("a").alias("v")).agg(F.min("label").alias("near"))
        step = kept(labels.join(near, "v").select("v", F.least("label", "near").alias("label"), F.col("label").alias("old")))
        jump = step.select(F.col("v").alias("label"), F.col("label").alias("further"))
        new = kept(step.join(jump, "label", "left").select("v", F.least("label", F.coalesce("further", "label")).alias("label"), "old"))
        if new.where("label != old").isEmpty():
            return new.select("v", "label")
        labels = new.select("v", "label")
