"""Grammars as tables: compress, explode to rules, validate, annotate, expand, share."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import cuts
from ..functions import grammar as G
from ..model import SLP
from ..session import kept, parts, workers


AT_ONCE = 100_000  # rules, or rows of them, held as Python objects at a time


def _rows(b: pa.RecordBatch, *names: str):
    """Rows one after another: the lists of a batch's grammars would be large as Python objects all at once."""
    cols = [b.column(n) for n in names]
    for k in range(b.num_rows):
        yield tuple(_value(c[k]) for c in cols)


def _value(x: pa.Scalar):
    if isinstance(x, pa.ListScalar) and x.is_valid and not x.values.null_count and pa.types.is_integer(x.type.value_type):
        return x.values.to_numpy().tolist()
    return x.as_py()


def _pieces(rows, names: list[str], types: list[pa.DataType], weight=lambda row: 1) -> Iterator[pa.RecordBatch]:
    """Batches of rows with a weight of AT_ONCE, or one row more."""
    out, held = [], 0
    for row in rows:
        out.append(row)
        held += weight(row)
        if held >= AT_ONCE:
            yield _batch(out, names, types)
            out, held = [], 0
    yield _batch(out, names, types)


def _batch(rows: list[tuple], names: list[str], types: list[pa.DataType]) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [()] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types)], names)


I32, I64, STR, INTS = pa.int32(), pa.int64(), pa.string(), pa.list_(pa.int32())
SLP_NAMES = ["string_id", "codec", "size", "length", "depth", "lhs", "rhs"]
SLP_TYPES = [I64, STR, I32, I64, I32, INTS, INTS]


def compress(strings: DataFrame, codec: str = "lz78") -> DataFrame:
    """One packed grammar per string. A null or empty string has none (every rule derives a letter) and gives no row."""
    if codec != "auto":
        G.codec(codec)  # an unsupported name fails here, not in a task
    workers(strings.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = ((ident, G.compress(text, codec), len(text)) for ident, text in _rows(b, "string_id", "text"))
            yield from _pieces(((i, codec, len(g), n, g.depths()[-1], g.lhs, g.rhs) for i, g, n in made), SLP_NAMES, SLP_TYPES, lambda row: row[2])

    rows = strings.select(F.col("string_id").cast("long").alias("string_id"), "text").where("text IS NOT NULL AND text != ''")
    return rows.mapInArrow(run, SLP)


def sizes(strings: DataFrame, codecs: tuple[str, ...]) -> DataFrame:
    """(string_id, codec, variables, letters) of each string under each codec, from one pass over the strings: sizes only,
    no rule leaves a task. Strings are dealt out by id, since a file may be a single task's. Null and empty strings give
    no row, as in compress."""
    for c in codecs:
        G.codec(c)
    workers(strings.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = ((ident, c, G.rule_count(text, c), len(text)) for ident, text in _rows(b, "string_id", "text") for c in codecs)
            yield from _pieces(rows, ["string_id", "codec", "variables", "letters"], [I64, STR, I32, I64])

    rows = strings.select(F.col("string_id").cast("long").alias("string_id"), "text").where("text IS NOT NULL AND text != ''")
    dealt = rows.repartition(4 * parts(strings.sparkSession), F.xxhash64("string_id"))
    return dealt.mapInArrow(run, "string_id long, codec string, variables int, letters long")


def best_slp(strings: DataFrame, codecs: tuple[str, ...] = ("rle", "lz78", "lzw", "words", "balanced")) -> DataFrame:
    """The smallest of several grammars of each string; ties by name."""
    every = compress(strings, codecs[0])
    for c in codecs[1:]:
        every = every.unionByName(compress(strings, c))
    pick = every.groupBy("string_id").agg(F.min_by(F.struct(*SLP_NAMES[1:]), F.struct("size", "codec")).alias("s"))
    return pick.select("string_id", "s.*")


def words_table(spark, family: str, ks: list[int], letters: str = "ab") -> DataFrame:
    """Grammars of named words; string_id is k."""
    rows = []
    for k in ks:
        s = G.word(family, k, letters)
        rows.append((k, family, len(s), s.lengths()[-1], s.depths()[-1], s.lhs, s.rhs))
    return spark.createDataFrame(rows, SLP)


def words_of(letters: DataFrame, family: str, ks: list[int]) -> DataFrame:
    """Grammars of named words over each row's (string_id, text) first two letters: (string_id, k, and the grammar's
    own columns). A text of fewer letters gives no row."""
    workers(letters.sparkSession)

    def run(batches):
        for b in batches:
            out = []
            for ident, text in _rows(b, "string_id", "text"):
                for k in ks:
                    s = G.word(family, k, text)
                    out.append((ident, k, family, len(s), s.lengths()[-1], s.depths()[-1], s.lhs, s.rhs))
            yield _batch(out, ["string_id", "k", *SLP_NAMES[1:]], [I64, I64, *SLP_TYPES[1:]])

    return letters.select("string_id", "text").where("length(text) >= 2").mapInArrow(run, "string_id long, k long, codec string, size int, length long, depth int, lhs array<int>, rhs array<int>")


def stats(slps: DataFrame) -> DataFrame:
    return slps.select("string_id", "codec", F.col("size").alias("variables"), F.col("length").alias("letters"), (F.col("length") / F.col("size")).alias("ratio"), "depth")


def expand(slps: DataFrame) -> DataFrame:
    """(string_id, codec, text)."""
    workers(slps.sparkSession)

    def run(batches):
        for b in batches:
            yield _batch([(i, c, G.Slp(l, r).expand()) for i, c, l, r in _rows(b, "string_id", "codec", "lhs", "rhs")], ["string_id", "codec", "text"], [I64, STR, STR])

    return slps.select("string_id", "codec", "lhs", "rhs").mapInArrow(run, "string_id long, codec string, text string")


def substr(slps: DataFrame, start: int, count: int) -> DataFrame:
    """count letters from start (from 0) of each text, without expanding it."""
    workers(slps.sparkSession)

    def run(batches):
        for b in batches:
            yield _batch([(i, G.Slp(l, r).substr(start, count)) for i, l, r in _rows(b, "string_id", "lhs", "rhs")], ["string_id", "text"], [I64, STR])

    return slps.select("string_id", "lhs", "rhs").mapInArrow(run, "string_id long, text string")


def rules(slps: DataFrame) -> DataFrame:
    """Packed grammars as one row per rule."""
    one = F.explode(F.expr("transform(arrays_zip(lhs, rhs), (r, k) -> struct(k AS var, r.lhs AS a, r.rhs AS b))"))
    r = slps.select(F.col("string_id").alias("gid"), one.alias("r"))
    term = F.col("r.a") < 0
    none = F.lit(None).cast("int")
    return r.select("gid", F.col("r.var").alias("var"), F.when(term, "letter").otherwise("pair").alias("kind"), F.when(term, F.col("r.b")).alias("sym"), F.when(term, none).otherwise(F.col("r.a")).alias("lhs"), F.when(term, none).otherwise(F.col("r.b")).alias("rhs"))


def packed(rule_rows: DataFrame, codec: str = "rules") -> DataFrame:
    """Rule rows back to packed grammars; a grammar is a row, as its text is."""
    g = rule_rows.groupBy("gid").agg(F.array_sort(F.collect_list(F.struct("var", F.coalesce("lhs", F.lit(-1)).alias("a"), F.coalesce("rhs", "sym").alias("b")))).alias("r"))
    g = g.select(F.col("gid").alias("string_id"), F.expr("transform(r, x -> x.a)").alias("lhs"), F.expr("transform(r, x -> x.b)").alias("rhs"))
    workers(g.sparkSession)

    def run(batches):
        for b in batches:
            out = []
            for i, l, r in _rows(b, "string_id", "lhs", "rhs"):
                s = G.Slp(l, r).normalised()
                out.append((i, codec, len(s), s.lengths()[-1], s.depths()[-1], s.lhs, s.rhs))
            yield _batch(out, SLP_NAMES, SLP_TYPES)

    return g.mapInArrow(run, SLP)


def validate(rule_rows: DataFrame) -> DataFrame:
    """Violations (gid, var, problem): a rule of neither shape, a child not before it, a missing child, two definitions."""
    shape = rule_rows.where("NOT ((kind = 'letter' AND sym IS NOT NULL AND lhs IS NULL AND rhs IS NULL) OR (kind = 'pair' AND sym IS NULL AND lhs IS NOT NULL AND rhs IS NOT NULL))")
    order = rule_rows.where("kind = 'pair' AND (lhs >= var OR rhs >= var)")
    twice = rule_rows.groupBy("gid", "var").count().where("count > 1")
    used = rule_rows.where("kind = 'pair'").select("gid", "var", F.explode(F.array("lhs", "rhs")).alias("child"))
    lost = used.join(rule_rows.select("gid", F.col("var").alias("child")), ["gid", "child"], "left_anti")
    out = None
    for df, problem in ((shape, "shape"), (order, "order"), (twice, "twice"), (lost, "missing child")):
        part = df.select("gid", "var", F.lit(problem).alias("problem")).distinct()
        out = part if out is None else out.unionByName(part)
    return out


def annotate(rule_rows: DataFrame) -> DataFrame:
    """Length and depth of every variable, level by level: each round settles the rules whose children are settled.

    The number of rounds is the depth of the deepest grammar; grammars of thousands of levels are better annotated
    in packed form (compress gives length and depth).
    """
    done = kept(rule_rows.where("kind = 'letter'").select("gid", "var", F.lit(1).cast("long").alias("len"), F.lit(0).alias("depth")))
    todo = kept(rule_rows.where("kind = 'pair'").select("gid", "var", "lhs", "rhs"))
    while True:
        l = done.select("gid", F.col("var").alias("lhs"), F.col("len").alias("l_len"), F.col("depth").alias("l_depth"))
        r = done.select("gid", F.col("var").alias("rhs"), F.col("len").alias("r_len"), F.col("depth").alias("r_depth"))
        new = kept(todo.join(l, ["gid", "lhs"]).join(r, ["gid", "rhs"]).select("gid", "var", (F.col("l_len") + F.col("r_len")).alias("len"), (F.greatest("l_depth", "r_depth") + 1).alias("depth")))
        if new.isEmpty():
            return done
        todo = kept(todo.join(new, ["gid", "var"], "left_anti"))
        done = kept(done.unionByName(new))


def fingerprints(slps: DataFrame) -> DataFrame:
    """(string_id, var, fp1, fp2, len): the same for equal texts in all grammars."""
    workers(slps.sparkSession)

    def run(batches):
        for b in batches:
            out = ((i, v, *f) for i, l, r in _rows(b, "string_id", "lhs", "rhs") for v, f in enumerate(G.Slp(l, r).fingerprints()))
            yield from _pieces(out, ["string_id", "var", "fp1", "fp2", "len"], [I64, I32, I64, I64, I64])

    return slps.select("string_id", "lhs", "rhs").mapInArrow(run, "string_id long, var int, fp1 long, fp2 long, len long")


def start_fingerprints(slps: DataFrame) -> DataFrame:
    """(string_id, fp1, fp2, len) of each grammar's start only: one row a string."""
    workers(slps.sparkSession)

    def run(batches):
        for b in batches:
            out = ((i, *G.Slp(l, r).fingerprints()[-1]) for i, l, r in _rows(b, "string_id", "lhs", "rhs"))
            yield from _pieces(out, ["string_id", "fp1", "fp2", "len"], [I64, I64, I64, I64])

    return slps.select("string_id", "lhs", "rhs").mapInArrow(run, "string_id long, fp1 long, fp2 long, len long")


def share_grammars(slps: DataFrame) -> DataFrame:
    """How often each text of a variable occurs over all grammars: (fp1, fp2, len, grammars, first). Partial sums
    before the shuffle keep frequent texts (single letters, blanks) from weighing on one task."""
    return fingerprints(slps).groupBy("fp1", "fp2", "len").agg(F.count("*").alias("grammars"), F.min(F.struct("string_id", "var")).alias("first"))


def concat_slp(a: DataFrame, b: DataFrame) -> DataFrame:
    """Grammars of the joined texts of rows with equal string_id."""
    workers(a.sparkSession)

    def run(batches):
        for x in batches:
            out = []
            for i, l1, r1, l2, r2 in _rows(x, "string_id", "lhs", "rhs", "lhs2", "rhs2"):
                s = G.concatenated([G.Slp(l1, r1), G.Slp(l2, r2)])
                out.append((i, "concat", len(s), s.lengths()[-1], s.depths()[-1], s.lhs, s.rhs))
            yield _batch(out, SLP_NAMES, SLP_TYPES)

    both = a.select("string_id", "lhs", "rhs").join(b.select("string_id", F.col("lhs").alias("lhs2"), F.col("rhs").alias("rhs2")), "string_id")
    return both.mapInArrow(run, SLP)


def power_slp(slps: DataFrame, times: int) -> DataFrame:
    return _each(slps, lambda s: G.powered(s, times), "power")


def reverse_slp(slps: DataFrame) -> DataFrame:
    return _each(slps, G.reversed_, "reverse")


def normalise(slps: DataFrame) -> DataFrame:
    return _each(slps, lambda s: s.normalised(), None)


def _each(slps: DataFrame, f, codec: str | None) -> DataFrame:
    workers(slps.sparkSession)

    def run(batches):
        for b in batches:
            out = []
            for i, c, l, r in _rows(b, "string_id", "codec", "lhs", "rhs"):
                s = f(G.Slp(l, r))
                out.append((i, codec or c, len(s), s.lengths()[-1], s.depths()[-1], s.lhs, s.rhs))
            yield _batch(out, SLP_NAMES, SLP_TYPES)

    return slps.select("string_id", "codec", "lhs", "rhs").mapInArrow(run, SLP)


def rle_runs(letters: DataFrame, key: str, order: list[str], letter: str) -> DataFrame:
    """Runs of equal letters of each key's row sequence: (key, run, letter, length), by window functions alone.

    A key's rows are one sequence, so they are in one window; its size is that of the string they make."""
    w = Window.partitionBy(key).orderBy(*order)
    new = (F.lag(letter).over(w).isNull() | (F.lag(letter).over(w) != F.col(letter))).cast("int")
    runs = letters.withColumn("_n", new).withColumn("run", F.sum("_n").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return runs.groupBy(key, "run", letter).agg(F.count("*").alias("length"))


def strings_from_rows(rows: DataFrame, key: str, order: list[str], letter: str) -> DataFrame:
    """(string_id, text): the letters of each key's rows in order. A text is one row in any case."""
    own = F.struct(*order, F.col(letter).alias("_c"))
    return rows.groupBy(F.col(key).alias("string_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(own)), lambda x: x["_c"]), "").alias("text"))


def corpus_pairs(strings: DataFrame, rounds: int = 8, least: int = 2) -> tuple[DataFrame, list[tuple[str, str, int]]]:
    """Pair replacement over a whole corpus: every round counts neighbouring tokens of all strings and joins the most
    frequent pair. Returns (string_id, tokens) and the merges. Counts are summed before they are shuffled."""
    cur = kept(strings.where("text != ''").select("string_id", F.split("text", "").alias("tokens")))
    merges = []
    for _ in range(rounds):
        two = cur.select(F.explode(F.expr("transform(sequence(1, greatest(size(tokens) - 1, 1)), k -> struct(tokens[k - 1] AS a, tokens[k] AS b))")).alias("p")).where("p.b IS NOT NULL")
        top = two.groupBy("p.a", "p.b").count().orderBy(F.desc("count"), "a", "b").first()
        if top is None or top["count"] < least:
            break
        merges.append((top["a"], top["b"], top["count"]))
        x, y = F.lit(top["a"]), F.lit(top["b"])
        step = lambda acc, t: F.when((F.element_at(acc, -1) == x) & (t == y), F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.concat(x, y)))).otherwise(F.concat(acc, F.array(t)))  # noqa: E731,B023
        first = F.slice("tokens", 1, 1)
        cur = kept(cur.select("string_id", F.aggregate(F.slice("tokens", F.lit(2), F.size("tokens")), first, step).alias("tokens")))
    return cur, merges


# --- partitions -----------------------------------------------------------------------------------------------------


def x_partition(strings: DataFrame, x: int, partition: str = "grammar", codec: str = "lz78") -> DataFrame:
    """Segments of every string: (string_id, x, seg_no, sym_id, start, len, role, piece), piece being their text."""
    workers(strings.sparkSession)
    names = ["string_id", "x", "seg_no", "sym_id", "start", "len", "role", "piece"]
    types = [I64, I32, I32, I32, I64, I32, STR, STR]

    def run(batches):
        for b in batches:
            out = []
            for i, text in _rows(b, "string_id", "text"):
                c = cuts.cut(text, x, partition, codec)
                out += [(i, x, k, s, at, c.size[s], c.roles.get(s, "gap"), text[at : at + c.size[s]]) for k, (s, at) in enumerate(zip(c.segments, c.starts()))]
                if len(out) > 100_000:
                    yield _batch(out, names, types)
                    out = []
            yield _batch(out, names, types)

    return strings.where("text IS NOT NULL AND text != ''").select(F.col("string_id").cast("long").alias("string_id"), "text").mapInArrow(run, "string_id long, x int, seg_no int, sym_id int, start long, len int, role string, piece string")


def partition_report(segments: DataFrame) -> DataFrame:
    """What a partition promises, measured: letters covered, joined text's hash, longest segment, distinct symbols."""
    g = segments.groupBy("string_id", "x").agg(F.sum("len").alias("covered"), F.max("len").alias("longest"), F.count("*").alias("segments"), F.size(F.collect_set("sym_id")).alias("symbols"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seg_no", "piece"))), lambda r: r["piece"]), "").alias("joined"), F.size(F.collect_set(F.struct("sym_id", F.xxhash64("piece")))).alias("texts"))
    return g.select("string_id", "x", "covered", "longest", "segments", "symbols", (F.col("texts") == F.col("symbols")).alias("one_text"), F.md5("joined").alias("joined_md5"))


def grid_partition(segments_a: DataFrame, segments_b: DataFrame, pairs: DataFrame) -> DataFrame:
    """How many blocks each pair of symbols of a pair has: from counts by symbol, never block by block."""
    count = lambda s, side: s.groupBy(F.col("string_id").alias(f"{side}_id"), F.col("sym_id").alias(f"{side}_sym")).agg(F.count("*").alias(f"n_{side}"))
    both = pairs.join(count(segments_a, "a"), "a_id").join(count(segments_b, "b"), "b_id")
    return both.groupBy("pair_id").agg(F.sum(F.col("n_a") * F.col("n_b")).alias("blocks"), F.count("*").alias("distinct_pairs"))
