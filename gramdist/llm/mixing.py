"""Mixing sources to target weights, with DataFrame operations only.

Each source's documents are permuted by a keyed hash and cut by its leading bits into equal ranges, the blocks, of
some WORDS_PER_BLOCK words however large the source. Where the part of a pass ends is found by counting cells within
cells, so only one cell of about a block's size is ever ordered document by document.
A source's target in words gives the number of whole passes over its blocks and a part of one more pass; those
block slots are its quota. A splitting tree deals the quotas to output shards: every node draws half of its
slots at random for its left child, so the counts by source in a child follow the multivariate hypergeometric
law and the quotas stay exact. A shard holds disjoint blocks, and its rows are ordered by another hash.

Nulls and ties: a null text has size 0 and is never taken; a null source is one source, last in order; rows
that share an id and text share their place in the permutation and are taken one by one. Repeated runs agree,
since every choice is a hash of the seed. An empty table gives no rows. Input columns named like an output
column are replaced. Documents are taken whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, boxed, table, unboxed, without, written

WEIGHTS = (5, 2, 1)
MAX_REPEAT = 3
STEP_BITS = 12  # cells that a level of the search for a source's edge looks at: 4096 a source
WORDS_PER_BLOCK = 1 << 16
WORDS_PER_SHARD = 1 << 24
MADE = ("size", "source_size", "target", "shards", "copies", "taken")


def place(seed: int, *cols: Column) -> Column:
    """60 bits of an MD5: the same numbers in any SQL engine."""
    key = F.concat_ws(":", F.lit(str(seed)), *[F.coalesce(c.cast("string"), F.lit("")) for c in cols])
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 15), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_repeat: int = MAX_REPEAT) -> DataFrame:
    """One row a source: size, weight, target. Targets are min(level * weight, max_repeat * size), the level being
    the one at which they sum to all sizes; it is found by a running sum over sources in order of their caps."""
    by = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by = by.withColumn("k", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    pick = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod("k", F.lit(len(weights))) + 1).cast("int"))
    by = by.withColumn("weight", pick).withColumn("cap", F.lit(max_repeat) * F.col("source_size"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), "k")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    by = by.withColumns({"left": F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0)), "open": F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing))})
    # the level if this source and all with larger caps stay uncapped; it is right at the first that it doesn't cap
    by = by.withColumn("level", F.col("left") / F.col("open")).withColumn("ok", F.col("level") * F.col("weight") <= F.col("cap"))
    by = by.withColumn("level", F.first(F.when(F.col("ok"), F.col("level")), ignorenulls=True).over(Window.orderBy(F.col("cap") / F.col("weight"), "k").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    target = F.least(F.coalesce(F.col("level") * F.col("weight"), F.col("cap").cast("double")), F.col("cap").cast("double"))
    return by.select("source", "source_size", "weight", target.alias("target"))


def mix(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, max_repeat: int = MAX_REPEAT, seed: int = 17, depth: int | None = None, words_per_block: int = WORDS_PER_BLOCK, columns: list[str] | None = None) -> DataFrame:
    """Every row of df (its columns, or those named) with its size, its source's size and target, the shards that
    drew it, copies (how many did) and taken (their words)."""
    columns = df.columns if columns is None else columns
    made, goal = _copies(df, id_col, text_col, source_col, weights, max_repeat, seed, columns, words_per_block)
    return drawn(made, goal, depth, words_per_block, seed).select(*unboxed(without(columns, *MADE)), *MADE)


def _copies(df, id_col, text_col, source_col, weights, max_repeat, seed, columns, words_per_block):
    words = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long")
    plain = df.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), words.alias("size"), place(seed, F.col(id_col)).alias("h"))
    plain = written(plain)
    targets = written(source_targets(plain, weights, max_repeat))
    same = lambda a, b: F.col(a).eqNullSafe(F.col(b))
    pos = plain.where("size > 0")
    goal = targets.select(F.col("source").alias("s"), "source_size", "target", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long").alias("passes"))
    goal = goal.withColumn("part", F.col("target") - F.col("passes") * F.col("source_size"))
    largest = targets.agg(F.max("source_size")).first()[0] or 0
    levels = max(1, -(-max(largest // words_per_block, 1).bit_length() // STEP_BITS))
    # the last cell: the first whose end is past the part of a pass that is due; then the last cell within it
    edge = goal.withColumns({"edge": F.lit(0).cast("long"), "before": F.lit(0).cast("long")})
    run = Window.partitionBy("s").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    for k in range(levels):
        inside = pos.join(edge.select("s", "edge", "before", "part"), same("source", "s") & (F.shiftright("h", 60 - STEP_BITS * k) == F.col("edge")))
        cells = inside.groupBy("s", "before", "part", F.shiftright("h", 60 - STEP_BITS * (k + 1)).alias("cell")).agg(F.sum("size").alias("n"))
        cells = cells.withColumn("before", F.col("before") + F.coalesce(F.sum("n").over(run), F.lit(0)))
        least = cells.where("before + n > part").groupBy("s").agg(F.min(F.struct("cell", "before")).alias("e"))
        edge = written(goal.join(least.select(F.col("s").alias("s2"), F.col("e.cell").alias("edge"), F.col("e.before").alias("before")), same("s", "s2"), "left").drop("s2"))
    bits = STEP_BITS * levels
    cell = F.shiftright("h", 60 - bits)
    pos = pos.withColumn("cell", cell)
    last = pos.join(edge.select("s", "edge", "before", "part"), same("source", "s") & (F.col("cell") == F.col("edge")))
    inside = Window.partitionBy("source").orderBy("h", "id").rowsBetween(Window.unboundedPreceding, 0)
    taken = last.withColumn("end", F.col("before") + F.sum("size").over(inside)).where("end <= part")
    cut = taken.groupBy("s").agg(F.max("end").alias("reached"), F.max(F.struct("h", "id")).alias("upto"))
    goal = edge.join(cut.withColumnRenamed("s", "s2"), same("s", "s2"), "left").drop("s2")
    goal = goal.withColumns({"reached": F.coalesce("reached", F.col("before"), F.lit(0)), "h_to": F.col("upto.h"), "id_to": F.col("upto.id"), "edge_bits": F.lit(bits)}).drop("upto")
    goal = written(goal)
    # of what is left, the one largest document that still fits closes most of the gap
    inside = F.col("edge").isNotNull() & ((F.col("cell") < F.col("edge")) | ((F.col("cell") == F.col("edge")) & F.coalesce((F.col("h") < F.col("h_to")) | ((F.col("h") == F.col("h_to")) & (F.col("id") <= F.col("id_to"))), F.lit(False))))
    fits = pos.join(goal, same("source", "s")).where(~inside & (F.col("size") <= F.col("part") - F.col("reached")))
    top = written(fits.groupBy("s").agg(F.max(F.struct("size", F.col("h"), "id")).alias("top")).select("s", F.col("top.h").alias("top_h"), F.col("top.id").alias("top_id")))
    goal = goal.join(top.withColumnRenamed("s", "s2"), same("s", "s2"), "left").drop("s2")
    goal = written(goal)
    out = df.select(boxed(df, columns), F.col(id_col).alias("id"), F.col(source_col).alias("source"), words.alias("size"), place(seed, F.col(id_col)).alias("h")).withColumn("cell", cell)
    names = {c: f"g_{c}" for c in goal.columns}
    wide = out.join(goal.select(*[F.col(c).alias(n) for c, n in names.items()]), F.col("source").eqNullSafe(F.col("g_s")), "left")
    ident = F.col("id")
    inside = F.col("g_edge").isNotNull() & ((F.col("cell") < F.col("g_edge")) | ((F.col("cell") == F.col("g_edge")) & F.coalesce((F.col("h") < F.col("g_h_to")) | ((F.col("h") == F.col("g_h_to")) & (ident <= F.col("g_id_to"))), F.lit(False))))
    extra = inside | F.coalesce((F.col("h") == F.col("g_top_h")) & (ident == F.col("g_top_id")), F.lit(False))
    copies = F.when(F.col("size") > 0, F.col("g_passes") + extra.cast("long")).otherwise(F.lit(0)).cast("long")
    made = wide.select("_row", "id", "source", "h", "size", F.col("g_source_size").alias("source_size"), F.col("g_target").alias("target"), copies.alias("due"))
    return made, goal


def block_bits(words: Column, words_per_block: int) -> Column:
    return F.ceil(F.log2(F.greatest(words / words_per_block, F.lit(1.0)))).cast("int")


def quota_slots(goal: DataFrame, words_per_block: int) -> DataFrame:
    """One row for each block of each pass that a source's target takes."""
    bits = block_bits(F.col("source_size"), words_per_block)
    g = goal.where("source_size > 0").withColumn("bits", bits).withColumn("epoch", F.explode(F.expr("sequence(0L, passes)")))
    g = g.withColumn("block", F.explode(F.expr("sequence(0L, shiftleft(1L, bits) - 1)")))
    # the part of a pass takes the blocks up to the last cell's, and the block of the document that fills the gap
    due = "epoch < passes OR (part > 0 AND block <= shiftright(edge, edge_bits - bits)) OR coalesce(block = shiftright(top_h, 60 - bits), false)"
    return g.where(due).select(F.col("s").alias("source"), "epoch", "block")


def splitting_tree(slots: DataFrame, depth: int, seed: int) -> DataFrame:
    """Deal slots to 2**depth shards: at every level each node keeps a uniformly random half for its left child."""
    out = slots.withColumn("shard", F.lit(0).cast("long"))
    for level in range(depth):
        at = Window.partitionBy("shard").orderBy(place(seed + level + 1, F.col("shard"), F.col("source"), F.col("epoch"), F.col("block")), "source", "epoch", "block")
        size = F.count("*").over(Window.partitionBy("shard"))
        out = out.withColumn("right", (F.row_number().over(at) > F.ceil(size / 2)).cast("long")).withColumn("shard", F.col("shard") * 2 + F.col("right")).drop("right")
    return out


def depth_for(goal: DataFrame) -> int:
    """Levels of the tree that give shards of about WORDS_PER_SHARD words."""
    words = goal.agg(F.sum("source_size")).first()[0] or 0
    return max(0, (words // WORDS_PER_SHARD).bit_length())


def drawn(made: DataFrame, goal: DataFrame, depth: int | None, words_per_block: int, seed: int) -> DataFrame:
    """Deal the block slots to shards and let every row look up the shards of its block: one for each pass it is due
    in. A block has at most max_repeat + 1 slots, so what a row meets is small."""
    depth = depth_for(goal) if depth is None else depth
    slots = splitting_tree(quota_slots(goal, words_per_block), depth, seed)
    by = slots.groupBy("source", "block").agg(F.array_sort(F.collect_list(F.struct("epoch", "shard"))).alias("slots"))
    by = written(by.select(F.col("source").alias("_s"), F.col("block").alias("_b"), "slots"))
    rows = made.withColumn("bits", block_bits(F.col("source_size"), words_per_block)).withColumn("block", F.expr("shiftright(h, 60 - bits)"))
    rows = rows.join(by, F.col("source").eqNullSafe(F.col("_s")) & (F.col("block") == F.col("_b")), "left")
    # the slot of the part of a pass is the last one, and a row due in it is due in all passes before
    shards = F.expr("coalesce(transform(filter(slots, x -> x.epoch < due), x -> x.shard), cast(array() AS array<bigint>))")
    return rows.withColumn("shards", shards).withColumn("copies", F.size("shards").cast("long")).withColumn("taken", F.col("copies") * F.col("size"))


def mix_rows(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, max_repeat: int = MAX_REPEAT, seed: int = 17, depth: int | None = None, words_per_block: int = WORDS_PER_BLOCK) -> DataFrame:
    """The mix itself: each row of df as often as it is taken, with its shard and its place in the shard's order.

    The place is a hash, so that sorting a shard (or a file of it) by it is the local shuffle. A shard is not one
    task: the tree only labels rows. depth None gives shards of about WORDS_PER_SHARD words.
    """
    return _placed(df, id_col, text_col, source_col, weights, max_repeat, seed, depth, words_per_block)[0]


def _placed(df, id_col, text_col, source_col, weights, max_repeat, seed, depth, words_per_block) -> tuple[DataFrame, int]:
    """(the mix, its number of shards)."""
    made, goal = _copies(df, id_col, text_col, source_col, weights, max_repeat, seed, df.columns, words_per_block)
    depth = depth_for(goal) if depth is None else depth
    rows = drawn(made, goal, depth, words_per_block, seed).select("_row", "id", F.posexplode("shards").alias("epoch", "shard"))
    return rows.select("_row", "shard", place(seed + 99, F.col("id"), F.col("epoch")).alias("place")).select(*unboxed(without(df.columns, "shard", "place")), "shard", "place"), 1 << depth


def mixed(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, max_repeat: int = MAX_REPEAT, seed: int = 17, depth: int | None = None, words_per_block: int = WORDS_PER_BLOCK) -> DataFrame:
    """The rows of the mix with exactly the columns of df, whatever their names: drawn by shard, a shard within one
    partition and in its shuffled order. This is the one place where texts move."""
    rows, shards = _placed(df.select(boxed(df)), f"_row.`{id_col}`", f"_row.`{text_col}`", f"_row.`{source_col}`", weights, max_repeat, seed, depth, words_per_block)
    n = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 2 * shards)
    return rows.repartition(n, "shard").sortWithinPartitions("shard", "place").select("_row.*")


def op8_mix_sources(spark, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"), columns=["doc_id"]).select("doc_id", "size", "source_size", "target", "taken", "copies")


ORACLE = """
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS size,
         CAST('0x' || substr(md5('17:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS h
  FROM documents),
src AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS k
  FROM d GROUP BY source),
wt AS (SELECT *, CASE k % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS weight, 3 * source_size AS cap FROM src),
lv AS (
  SELECT *, CAST(sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / weight, k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE)
       / sum(weight) OVER (ORDER BY cap / weight, k ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM wt),
ok AS (SELECT arg_min(level, [cap / weight, k]) AS level FROM lv WHERE level * weight <= cap),
tg AS (
  SELECT source, source_size, least(coalesce((SELECT level FROM ok) * weight, CAST(cap AS DOUBLE)), CAST(cap AS DOUBLE)) AS target FROM wt),
pt AS (
  SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS passes FROM tg),
e AS (
  SELECT d.doc_id, d.size, d.h, p.source, p.source_size, p.target, p.passes, p.target - p.passes * p.source_size AS part,
         sum(d.size) OVER (PARTITION BY d.source ORDER BY d.h, d.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS at_end
  FROM d JOIN pt p ON d.source IS NOT DISTINCT FROM p.source),
r AS (SELECT source, coalesce(max(CASE WHEN size > 0 AND at_end <= part THEN at_end END), 0) AS reached FROM e GROUP BY source),
top AS (
  SELECT e.source, arg_max(e.doc_id, [e.size, e.h, e.doc_id]) AS top_id
  FROM e JOIN r ON e.source IS NOT DISTINCT FROM r.source
  WHERE e.size > 0 AND e.at_end > e.part AND e.size <= e.part - r.reached GROUP BY e.source)
SELECT e.doc_id, CAST(e.size AS BIGINT) AS size, e.source_size, e.target,
       CAST(CASE WHEN e.size > 0 THEN e.size * (e.passes + CASE WHEN e.at_end <= e.part OR e.doc_id = t.top_id THEN 1 ELSE 0 END) ELSE 0 END AS BIGINT) AS taken,
       CAST(CASE WHEN e.size > 0 THEN e.passes + CASE WHEN e.at_end <= e.part OR e.doc_id = t.top_id THEN 1 ELSE 0 END ELSE 0 END AS BIGINT) AS copies
FROM e LEFT JOIN top t ON e.source IS NOT DISTINCT FROM t.source
"""
