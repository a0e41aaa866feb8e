"""The experiment workloads on the given tables: each takes (spark, sf_dir) and reads whole tables and whole texts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .operators import distances as X
from .operators import grammars as S
from .operators import relational as R
from .operators import repository as repo
from .operators import similarity as sim
from .plans import planner
from .scoring import Scoring, check_metric, cost_rows, letter_classes
from .session import kept
from .sources.tables import load

SLOTS = 4320  # ten-minute slots of the events' thirty days


# --- strings ----------------------------------------------------------------------------------------------------------


def texts(spark, sf, table, id_col, text_col) -> DataFrame:
    return load(spark, sf, table, id_col, text_col).select(F.col(id_col).cast("long").alias("string_id"), F.col(text_col).alias("text"))


def event_words(spark, sf) -> DataFrame:
    e = load(spark, sf, "events", "user_id", "ts", "event_id", "event_type").withColumn("letter", F.upper(F.substring("event_type", 1, 1)))
    return S.strings_from_rows(e, "user_id", ["ts", "event_id"], "letter")


def timelines(spark, sf) -> DataFrame:
    """The last event's letter in each slot, standing until the next: the as-of value of every slot from the first."""
    e = load(spark, sf, "events", "user_id", "ts", "event_id", "event_type")
    e = e.withColumn("slot", F.expr(f"least(cast(floor(timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts) / 600) AS int), {SLOTS - 1})"))
    last = e.groupBy("user_id", "slot").agg(F.max_by(F.upper(F.substring("event_type", 1, 1)), F.struct("ts", "event_id")).alias("letter"))
    w = Window.partitionBy("user_id").orderBy("slot")
    run = last.withColumn("piece", F.repeat("letter", F.coalesce(F.lead("slot").over(w), F.lit(SLOTS)) - F.col("slot")))
    return S.strings_from_rows(run, "user_id", ["slot"], "piece")


def flag_words(spark, sf) -> DataFrame:
    l = load(spark, sf, "lineitem", "l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_returnflag")
    return S.strings_from_rows(l, "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey"], "l_returnflag")


def quantity_runs(spark, sf) -> DataFrame:
    l = load(spark, sf, "lineitem", "l_partkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_returnflag", "l_quantity")
    l = l.withColumn("piece", F.repeat("l_returnflag", F.col("l_quantity").cast("int")))
    return S.strings_from_rows(l, "l_partkey", ["l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_quantity"], "piece")


def status_words(spark, sf) -> DataFrame:
    o = load(spark, sf, "orders", "o_custkey", "o_orderdate", "o_orderkey", "o_orderstatus")
    return S.strings_from_rows(o, "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderstatus")


def sign_words(spark, sf) -> DataFrame:
    e = load(spark, sf, "embeddings", "vec_id", "embedding", "label")
    return e.select(F.col("vec_id").alias("string_id"), F.array_join(F.transform("embedding", lambda x: F.when(x >= 0, "1").otherwise("0")), "").alias("text"), "label")


def names(spark, sf) -> DataFrame:
    """Distinct part names, numbered in order; names are a fixed vocabulary."""
    p = load(spark, sf, "part", "p_name").where("p_name IS NOT NULL").distinct()
    return p.select((F.row_number().over(Window.orderBy("p_name")) - 1).cast("long").alias("string_id"), F.col("p_name").alias("text"))


# --- pairs ------------------------------------------------------------------------------------------------------------


def next_pairs(strings: DataFrame) -> DataFrame:
    """(pair_id, a, b): every string with the one whose id is the next number."""
    b = strings.select((F.col("string_id") - 1).alias("string_id"), F.col("text").alias("b"))
    return strings.select("string_id", F.col("text").alias("a")).join(b, "string_id").select(F.col("string_id").alias("pair_id"), "a", "b")


def ordered_pairs(strings: DataFrame, by: list[str]) -> DataFrame:
    """(pair_id, a, b): every string with the next larger id among those that agree on by."""
    w = Window.partitionBy(*by).orderBy("string_id")
    return strings.select(F.col("string_id").alias("pair_id"), F.col("text").alias("a"), F.lead("text").over(w).alias("b")).where("b IS NOT NULL")


def doc_pairs(spark, sf) -> DataFrame:
    d = load(spark, sf, "documents", "doc_id", "text", "lang")
    b = d.select((F.col("doc_id") - 1).alias("doc_id"), "lang", F.col("text").alias("b"))
    return d.select("doc_id", "lang", F.col("text").alias("a")).join(b, ["doc_id", "lang"]).select(F.col("doc_id").alias("pair_id"), "a", "b")


def near_copies(spark, sf) -> DataFrame:
    """Documents that share the least hash of their five-word shingles, each with the next of its kind: pair_id is
    both ids."""
    d = texts(spark, sf, "documents", "doc_id", "text")
    p = sim.shared_minima(d).withColumn("pair_id", F.concat_ws("-", "a_id", "b_id"))
    return X.with_texts(p, d)


def turn_pairs(spark, sf) -> DataFrame:
    c = load(spark, sf, "conversations", "conv_id", "turn", "role", "text")
    b = c.select("conv_id", (F.col("turn") - 2).alias("turn"), "role", F.col("text").alias("b"))
    return c.withColumnRenamed("text", "a").join(b, ["conv_id", "turn", "role"]).select((F.col("conv_id") * 1000 + F.col("turn")).alias("pair_id"), "a", "b")


def status_pairs(spark, sf) -> DataFrame:
    c = load(spark, sf, "customer", "c_custkey", "c_nationkey", "c_mktsegment")
    return ordered_pairs(status_words(spark, sf).join(c, F.col("string_id") == F.col("c_custkey")), ["c_nationkey", "c_mktsegment"])


def whole(df: DataFrame) -> DataFrame:
    return df.select("pair_id", F.col("distance").cast("long").alias("distance"))


def halves(df: DataFrame) -> DataFrame:
    return df.select("pair_id", F.round("distance", 6).alias("distance"))


# --- the workloads ------------------------------------------------------------------------------------------------------


def w01_unit_docs(spark, sf):
    return whole(X.unit_distance(doc_pairs(spark, sf)))


def w02_rational_event_words(spark, sf):
    return whole(X.rational_distance(next_pairs(event_words(spark, sf))))


def w03_arbitrary_benchmark(spark, sf):
    return halves(X.arbitrary_distance(next_pairs(texts(spark, sf, "benchmark", "item_id", "text")), letter_classes(), "lz78"))


def w04_rational_half_cost(spark, sf):
    return halves(X.rational_distance(next_pairs(names(spark, sf)), Scoring.rational(1, 1, 1.5)))


def w05_indel_urls(spark, sf):
    return whole(X.grammar_against_text(next_pairs(texts(spark, sf, "pages", "page_id", "url")), gap_only=True))


def w06_mixed_codecs(spark, sf):
    return whole(X.block_distance(next_pairs(event_words(spark, sf)), None, None, "grammar", "rle", "lz77"))


def w07_state_timelines(spark, sf):
    return whole(X.rle_distance(next_pairs(timelines(spark, sf))))


def w08_quantity_runs(spark, sf):
    return whole(X.rle_distance(next_pairs(quantity_runs(spark, sf))))


def w09_order_status(spark, sf):
    return whole(X.block_distance(status_pairs(spark, sf), None, 4, "grammar", "lzw"))


def w10_flags_four_russians(spark, sf):
    return whole(X.four_russians(next_pairs(flag_words(spark, sf)), t=3))


def w11_embedding_bits(spark, sf):
    return whole(X.block_distance(ordered_pairs(sign_words(spark, sf), ["label"]), None, 8, "uniform", "uniform"))


def w12_near_copies(spark, sf):
    return whole(X.unit_distance(near_copies(spark, sf)))


def w13_conversation_turns(spark, sf):
    return whole(X.unit_distance(turn_pairs(spark, sf)))


def w14_url_pairs(spark, sf):
    return whole(X.unit_distance(next_pairs(texts(spark, sf, "pages", "page_id", "url"))))


def w15_html_pages(spark, sf):
    return whole(X.unit_distance(next_pairs(texts(spark, sf, "pages", "page_id", "html"))))


def region_letters(spark, sf) -> list[str]:
    """Two different letters from each region's name; five regions."""
    return [r.r_name for r in load(spark, sf, "region", "r_name").orderBy("r_name").collect()]


def w16_fibonacci(spark, sf, ks=range(5, 19)):
    """Consecutive words over each region's first two letters, by their grammars: short programs of long texts."""
    out = None
    for n, name in enumerate(region_letters(spark, sf)):
        s = S.expand(S.words_table(spark, "fibonacci", list(ks), name[:2])).select((F.col("string_id") + 100 * n).alias("string_id"), "text")
        out = s if out is None else out.unionByName(s)
    p = next_pairs(out)
    return whole(X.block_distance(p, None, 64, "grammar", "pairs"))


def w17_example_word(spark, sf):
    """The first seven words over the last two letters of every supplier's name, by their grammars."""
    s = load(spark, sf, "supplier", "s_suppkey", "s_name").select(F.col("s_suppkey").cast("long").alias("string_id"), F.expr("right(s_name, 2)").alias("text"))
    g = S.words_of(s, "fibonacci", list(range(1, 8))).withColumn("string_id", F.col("string_id") * 10 + F.col("k"))
    return S.expand(g).select(F.expr("string_id div 10").alias("s_suppkey"), F.expr("string_id % 10").alias("k"), "text")


def supplier_ends(spark, sf) -> DataFrame:
    """The last four letters of every supplier's name."""
    return texts(spark, sf, "supplier", "s_suppkey", "s_name").withColumn("text", F.expr("right(text, 4)"))


def w18_example_block(spark, sf):
    """The boundary matrix of each supplier's last four letters against the next one's."""
    return R.dist_rows(next_pairs(supplier_ends(spark, sf))).select("pair_id", "i", "j", "w")


def w18_example_block_kernel(spark, sf):
    from .functions.udfs import DistCells
    from .session import workers

    workers(spark)
    p = next_pairs(supplier_ends(spark, sf))
    spark.udtf.register("gramdist_dist_cells", DistCells)
    p.createOrReplaceTempView("gramdist_block")
    return spark.sql("SELECT pair_id, c.i, c.j, CAST(c.w AS BIGINT) AS w FROM gramdist_block, LATERAL gramdist_dist_cells(a, b) c")


def w19_prefix_table(spark, sf):
    return R.dp_table(next_pairs(names(spark, sf))).select("pair_id", F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "value")


def w19_table_by_folds(spark, sf):
    return R.dp_distance_sql(next_pairs(names(spark, sf)))


def w19_table_by_paths(spark, sf):
    return R.lightest_path(R.grid_edges(next_pairs(names(spark, sf))))


def partition_query(x: int, partition: str = "grammar"):
    def run(spark, sf):
        d = kept(texts(spark, sf, "documents", "doc_id", "text").where("text != ''"))
        r = S.partition_report(S.x_partition(d, x, partition))
        small = F.lit(True) if partition in ("runs", "phrases") else F.col("longest") < 2 * max(x, 1)
        return r.select(F.col("string_id").alias("doc_id"), F.col("covered").cast("long").alias("covered"), (small | (F.col("longest") == 1)).alias("short_enough"), "one_text", "joined_md5")

    return run


def round_trip_query(codec: str, table: str = "documents", id_col: str = "doc_id", text_col: str = "text"):
    def run(spark, sf):
        t = S.expand(S.compress(texts(spark, sf, table, id_col, text_col), codec))
        return t.select("string_id", F.length("text").cast("long").alias("letters"), F.md5("text").alias("text_md5"))

    return run


def w22_flag_runs(spark, sf):
    l = load(spark, sf, "lineitem", "l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_returnflag")
    r = S.rle_runs(l, "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey"], "l_returnflag")
    return r.select("l_suppkey", F.col("run").cast("long").alias("run"), "l_returnflag", "length")


def w23_grammar_sizes(spark, sf):
    """Letters, variables and their ratio of every document under each linear-time compressor."""
    out = S.sizes(texts(spark, sf, "documents", "doc_id", "text"), ("rle", "lz78", "lzw", "words", "balanced"))
    return out.groupBy("codec").agg(F.count("*").alias("strings"), F.sum("letters").alias("letters"), F.sum("variables").alias("variables"), F.round(F.sum("letters") / F.sum("variables"), 6).alias("ratio"))


def w24_repository_keys(spark, sf, x: int = 4):
    """Blocks and distinct block keys of the uniform cut, per pair of event words."""
    w = kept(event_words(spark, sf))
    cut = w.select("string_id", F.explode(F.expr(f"transform(sequence(0, cast((length(text) - 1) / {x} AS int)), k -> substring(text, k * {x} + 1, {x}))")).alias("sym"))
    n = cut.groupBy("string_id", "sym").agg(F.count("*").alias("n"))
    a = n.select(F.col("string_id").alias("pair_id"), F.col("sym").alias("a_sym"), F.col("n").alias("n_a"))
    b = n.select((F.col("string_id") - 1).alias("pair_id"), F.col("sym").alias("b_sym"), F.col("n").alias("n_b"))
    return a.join(b, "pair_id").groupBy("pair_id").agg(F.sum(F.col("n_a") * F.col("n_b")).alias("blocks"), F.count("*").alias("distinct_keys"))


def w25_bounds(spark, sf):
    """Each method's cost formula on the timelines, with runs for the grammar size."""
    t = timelines(spark, sf).select("string_id", planner.run_count(F.col("text")).cast("long").alias("variables"), F.length("text").cast("long").alias("letters"))
    t = t.withColumn("x", planner.choose_x(F.col("variables"), F.col("letters")))
    return t.select("string_id", "variables", "letters", "x", *[F.round(F.log2(planner.bound(k, F.col("variables"), F.col("letters"), F.col("x"))), 6).alias(k) for k in planner.BOUNDS])


def w25_best_side(spark, sf):
    t = timelines(spark, sf).select("string_id", planner.run_count(F.col("text")).cast("long").alias("variables"), F.length("text").cast("long").alias("letters"))
    return planner.cheapest_x(t).select("string_id", "variables", "letters", F.col("best_x").cast("long").alias("best_x"), F.round(F.log2("best_cost"), 6).alias("best_cost"), "closed_x")


def w26_cost_axioms(spark, sf):
    """Violations of the metric axioms by the costs of unequal gaps and shortcuts, over the letters of all part names."""
    s = Scoring(2, 1, 3, 1, "arbitrary", True, {"a": 3}, {}, {("a", "b"): 1, ("b", "c"): 1, ("a", "c"): 5})
    used = load(spark, sf, "part", "p_name").select(F.explode(F.split("p_name", "")).alias("x")).where("x != ''").distinct()
    alphabet = sorted(r.x for r in used.collect())  # letters of a vocabulary of names
    return check_metric(cost_rows(spark, s, "".join(alphabet))).groupBy("axiom").agg(F.count("*").alias("violations"), F.round(F.max("excess"), 6).alias("most"))


def w26_triangles(spark, sf):
    """Triangle checks of the distances among each part name and the two after it, every way round."""
    n = names(spark, sf)
    w = Window.orderBy("string_id")  # a vocabulary of names
    t = n.select("string_id", F.col("text").alias("a"), F.lead("text", 1).over(w).alias("b"), F.lead("text", 2).over(w).alias("c")).where("c IS NOT NULL")
    t = t.select(F.levenshtein("a", "b").alias("ab"), F.levenshtein("b", "c").alias("bc"), F.levenshtein("a", "c").alias("ac"))
    return t.agg(F.count("*").alias("triples"), F.coalesce(F.sum(F.expr("cast(ac > ab + bc OR ab > ac + bc OR bc > ab + ac AS bigint)")), F.lit(0)).alias("violations"), F.sum("ac").alias("letters"))


def w27_propagation(spark, sf):
    """Output values of each pair of names as one block: base values through its boundary matrix."""
    p = kept(next_pairs(names(spark, sf)))
    base = p.select("pair_id", F.explode(F.expr("transform(sequence(0, length(a) + length(b)), k -> struct(k AS i, abs(length(a) - k) AS v))")).alias("x")).select("pair_id", "x.i", "x.v")
    return R.propagate_rows(base, R.dist_rows(p)).select("pair_id", F.col("j").cast("long").alias("j"), F.col("v").cast("long").alias("v"))


def w28_merging(spark, sf):
    """Boundary matrices of a name against both halves of "the quick", merged."""
    n = names(spark, sf).select(F.col("string_id").alias("pair_id"), F.col("text").alias("a"), F.length("text").alias("p"))
    n = kept(n)
    out = None
    for (p,) in n.select("p").distinct().orderBy("p").collect():  # lengths of a vocabulary of names
        own = n.where(F.col("p") == p)
        m = R.merge_rows(R.dist_rows(own.select("pair_id", "a", F.lit("the q").alias("b"))), R.dist_rows(own.select("pair_id", "a", F.lit("uick").alias("b"))), p, 5)
        out = m if out is None else out.unionByName(m)
    return out.select("pair_id", F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "w")


def w29_side_sweep(spark, sf):
    """The distance of event words for every side of the blocks: the side moves the work, never the value."""
    p = kept(next_pairs(event_words(spark, sf)))
    out = None
    for x in (1, 2, 4, 8, 16, 32):
        d = whole(X.block_distance(p, None, x)).withColumn("x", F.lit(x).cast("long"))
        out = d if out is None else out.unionByName(d)
    return out


def w29_side_work(spark, sf):
    """What the side moves: blocks, distinct keys, merges, table entries, probes, by side."""
    p = kept(next_pairs(event_words(spark, sf)))
    out = None
    for x in (1, 2, 4, 8, 16, 32):
        c = X.block_distance(p, None, x).select(F.lit(x).alias("x"), *[F.col("counters")[k].alias(k) for k in ("blocks", "distinct", "merges", "entries", "probes", "cells")])
        out = c if out is None else out.unionByName(c)
    return out.groupBy("x").agg(*[F.coalesce(F.sum(k), F.lit(0)).alias(k) for k in ("blocks", "distinct", "merges", "entries", "probes", "cells")])


VARIANTS = {
    "dense": {}, "points": {"form": "points"}, "braids": {"form": "perm"}, "four_way": {"recursion": "four_way"},
    "halves": {"how": "halves"}, "elimination": {"how": "elimination"}, "vector": {"how": "vector"}, "monge_merge": {"merge": "vector"},
    "uniform": {"partition": "uniform"}, "runs": {"partition": "runs"}, "phrases": {"partition": "phrases"},
    "lz77": {"codec": "lz77"}, "lzw": {"codec": "lzw"}, "pairs": {"codec": "pairs"}, "rle": {"codec": "rle"}, "words": {"codec": "words"}, "balanced": {"codec": "balanced"},
}


def w30_variants_agree(spark, sf):
    """Order-status pairs by every variant and baseline: how many different values a pair has, and the value."""
    p = kept(status_pairs(spark, sf))
    every = [X.block_distance(p, None, 4 if "form" not in v else None, **v) for v in VARIANTS.values()]
    every += [X.dp_distance(p), X.bit_distance(p), X.four_russians(p), X.rle_distance(p), X.lz78_distance(p), X.grammar_against_text(p), X.grammar_against_text(p, merge="dense")]
    out = None
    for d in every:
        d = whole(d)
        out = d if out is None else out.unionByName(d)
    return out.groupBy("pair_id").agg(F.countDistinct("distance").alias("n_values"), F.count("*").alias("n_variants"), F.min("distance").alias("distance"))


def w31_similarity_join(spark, sf):
    return sim.similarity_join(names(spark, sf), 2)


def w32_nearest(spark, sf):
    """Every benchmark item's three nearest among all items."""
    b = texts(spark, sf, "benchmark", "item_id", "text")
    d = sim.nearest(b, b, 3)
    return d.select("query_id", "string_id", "distance", F.col("rank").cast("long").alias("rank"))


def w33_contained(spark, sf):
    """Benchmark items in documents: least distance to any window, for pairs that share a piece of 20 letters."""
    return sim.contained(texts(spark, sf, "benchmark", "item_id", "text"), texts(spark, sf, "documents", "doc_id", "text"), 20)


def w34_classes(spark, sf):
    """Classes of part names linked at distance 2 or less."""
    return sim.classes(sim.similarity_join(names(spark, sf), 2).select("a", "b")).select(F.col("v").alias("name"), "label")


def w35_quality_by_distance(spark, sf):
    """Near copies and their labels: mean distance by label."""
    l = load(spark, sf, "labels", "doc_id", "quality", "toxic").withColumnRenamed("doc_id", "pair_id")
    d = whole(X.unit_distance(near_copies(spark, sf))).withColumn("pair_id", F.split("pair_id", "-")[0].cast("long")).join(l, "pair_id", "left")
    return d.groupBy("quality", "toxic").agg(F.count("*").alias("pairs"), F.round(F.avg("distance"), 6).alias("mean_distance"))


def w35_distance_cube(spark, sf):
    """Distances of like-language neighbours by language and source, with all totals."""
    d = whole(X.unit_distance(doc_pairs(spark, sf))).join(load(spark, sf, "documents", "doc_id", "lang", "source").withColumnRenamed("doc_id", "pair_id"), "pair_id")
    return d.cube("lang", "source").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("pairs"), F.sum("distance").alias("distance"))


def w36_stream_running(spark, sf):
    """Distance of each user's event word to user 0's, kept row by row over the stream of events."""
    from .streaming import events as E

    first = event_words(spark, sf).orderBy("string_id").first()  # one string: the template
    stream = E.read_events(spark, f"{sf}/events.parquet")
    out = E.run_once(E.running_distance(stream, first["text"]), "update")
    return out.groupBy("user_id").agg(F.max_by("events", "epoch").alias("events"), F.max_by("distance", "epoch").cast("long").alias("distance"))


def w37_stream_windows(spark, sf):
    """Daily event strings from the stream against a fixed word."""
    from .streaming import events as E

    stream = E.window_strings(E.read_events(spark, f"{sf}/events.parquet"), "1 day")
    t = spark.createDataFrame([("word", "VCPCV")], "name string, template string")
    out = E.run_once(E.against(stream, t), "append")
    return out.select("user_id", F.date_format("start", "yyyy-MM-dd").alias("day"), "text", "distance")


def w38_shared_repository(spark, sf):
    """Event words through one repository for the whole workload, made level by level as tables."""
    w = kept(event_words(spark, sf))
    ids = w.select(F.col("string_id").alias("a_id"), (F.col("string_id") + 1).alias("b_id"))
    pairs = kept(ids.join(w.select(F.col("string_id").alias("b_id")), "b_id").select(F.col("a_id").alias("pair_id"), "a_id", "b_id"))
    return whole(repo.shared_distance(pairs, w, 2)[0])


def w39_grammar_against_text(spark, sf):
    return whole(X.grammar_against_text(next_pairs(event_words(spark, sf))))


def w40_lz78_phrases(spark, sf):
    return whole(X.lz78_distance(next_pairs(event_words(spark, sf))))


def w41_quadratic(spark, sf):
    return whole(X.dp_distance(next_pairs(flag_words(spark, sf))))


def w42_grammar_rules(spark, sf):
    """Lengths of all variables of the event words' grammars by joins level by level; the start's is the word's."""
    a = S.annotate(S.rules(S.compress(event_words(spark, sf), "lz78")))
    return a.groupBy(F.col("gid").alias("string_id")).agg(F.max("len").alias("letters"))


def w43_valid_rules(spark, sf):
    """Violations in the grammars of all event words and urls; none."""
    s = S.compress(event_words(spark, sf), "lz77").unionByName(S.compress(texts(spark, sf, "pages", "page_id", "url").withColumn("string_id", -F.col("string_id") - 1), "pairs"))
    return S.validate(S.rules(s)).groupBy("problem").agg(F.count("*").alias("rules"))


def w44_corpus_pairs(spark, sf):
    """Urls after eight rounds of pair replacement over all of them: the tokens still spell the texts."""
    cur, _ = S.corpus_pairs(texts(spark, sf, "pages", "page_id", "url"), 8)
    return cur.select("string_id", F.md5(F.array_join("tokens", "")).alias("text_md5"))


def w44_neighbour_counts(spark, sf):
    """How often letters follow each other in the event words: what a round of pair replacement counts."""
    w = event_words(spark, sf).select(F.explode(F.expr("transform(sequence(1, greatest(length(text) - 1, 1)), k -> substring(text, k, 2))")).alias("pair"))
    return w.where("length(pair) = 2").groupBy("pair").agg(F.count("*").alias("n"))


def w45_substrings(spark, sf):
    """Fifty letters from the hundredth of every document's grammar, without expanding it."""
    d = S.substr(S.compress(texts(spark, sf, "documents", "doc_id", "text"), "lz78"), 99, 50)
    return d.select("string_id", "text")


def w46_grammar_algebra(spark, sf):
    """Reversed, doubled and repeated urls through their grammars."""
    s = kept(S.compress(texts(spark, sf, "pages", "page_id", "url"), "lzw"))
    kinds = {"reverse": S.reverse_slp(s), "concat": S.concat_slp(s, s), "power": S.power_slp(s, 5), "normal": S.normalise(s)}
    out = None
    for k, v in kinds.items():
        e = S.expand(v).select("string_id", F.lit(k).alias("kind"), F.md5("text").alias("text_md5"))
        out = e if out is None else out.unionByName(e)
    return out


def w47_fingerprints(spark, sf):
    """Different texts and different fingerprints of the starts of two grammars each: as many."""
    d = texts(spark, sf, "documents", "doc_id", "text").where("text != ''")
    out = None
    for c in ("rle", "balanced"):
        top = S.start_fingerprints(S.compress(d, c)).select("string_id", F.struct("fp1", "fp2", "len").alias("f"))
        out = top if out is None else out.unionByName(top)
    return out.agg(F.countDistinct("f").alias("texts"))


def w48_shared_variables(spark, sf):
    """Variables of all event words' grammars and how many are the same text: what a shared repository saves."""
    g = S.share_grammars(S.compress(event_words(spark, sf), "lz78"))
    return g.groupBy("len").agg(F.count("*").alias("texts"), F.sum("grammars").alias("variables"))


def w49_border_values(spark, sf):
    """Distances of each event word to every prefix of the next, read off the last borders of the sweep."""
    return X.boundary_values(next_pairs(event_words(spark, sf)), 8, last=True).select("pair_id", "col", "value")


def w50_giant_pair(spark, sf, letters: int = 4096):
    """All events as one string against all orders as one string, in pieces of even ranges of their keys."""
    from .operators.tiled import tiled_pieces

    e = load(spark, sf, "events", "event_id", "event_type").select((F.col("event_id") / letters).cast("long").alias("k"), F.col("event_id").alias("o"), F.upper(F.substring("event_type", 1, 1)).alias("c"))
    o = load(spark, sf, "orders", "o_orderkey", "o_orderstatus").select((F.col("o_orderkey") / letters).cast("long").alias("k"), F.col("o_orderkey").alias("o"), F.col("o_orderstatus").alias("c"))
    a, b = (kept(S.strings_from_rows(x, "k", ["o"], "c").withColumnRenamed("string_id", "k")) for x in (e, o))
    n = [x.agg(F.sum(F.length("text"))).first()[0] for x in (a, b)]
    return spark.createDataFrame([(*n, int(tiled_pieces(a, b)))], "letters_a long, letters_b long, distance long")


def w51_banded(spark, sf):
    return whole(X.banded_distance(next_pairs(event_words(spark, sf)), 42))


def w52_sql_functions(spark, sf):
    """Registered functions from SQL: distances, ratios and segments of part names."""
    from .functions.udfs import register_all

    register_all(spark)
    next_pairs(names(spark, sf)).createOrReplaceTempView("gramdist_names")
    return spark.sql("""
      SELECT pair_id, CAST(edit_distance(a, b) AS BIGINT) AS distance, slp_expand(slp_of(a, 'lz78')) AS text,
             (SELECT array_join(transform(array_sort(collect_list(struct(s.seg_no, s.piece))), x -> x.piece), '') FROM segments('the quick brown fox', 4) s) AS cut
      FROM gramdist_names""")


def w53_windows_of_braids(spark, sf):
    """Least distance of each part name to any window of the next, from one braid of the two."""

    def kernel(a, b):
        from .functions import succinct as Q

        m, n = len(a), len(b)
        braid = Q.comb(Q.doubled(a), Q.doubled(b))
        return min(m + j - i - Q.common(braid, 2 * m, 2 * n, 2 * i, 2 * j) for i in range(n + 1) for j in range(i, n + 1)), {}

    return whole(X.by_kernel(next_pairs(names(spark, sf)), lambda: kernel))


def w54_token_dictionary(spark, sf):
    """The dictionary of all documents' tokens: how many there are of each length, and how often they are used."""
    t = load(spark, sf, "documents", "text").select(F.explode(F.split("text", " ")).alias("token")).where("token != ''")
    return t.groupBy("token").agg(F.count("*").alias("n")).groupBy(F.length("token").cast("long").alias("letters")).agg(F.count("*").alias("tokens"), F.sum("n").alias("uses"))


def w55_work_by_variant(spark, sf):
    """Counters of every variant on the order-status pairs, a column each."""
    p = kept(status_pairs(spark, sf))
    out = None
    for name, v in VARIANTS.items():
        c = X.block_distance(p, None, 4, **v).select(F.lit(name).alias("variant"), F.explode("counters").alias("counter", "n"))
        out = c if out is None else out.unionByName(c)
    return out.groupBy("variant").pivot("counter", ["blocks", "distinct", "tables", "merges", "leaves", "entries", "points", "probes", "cells"]).agg(F.sum("n"))


def w56_phase_seconds(spark, sf):
    """Wall seconds of the phases on the event words: compress, cut, repository, sweep, and the quadratic table."""
    import time

    w = kept(event_words(spark, sf))
    p = kept(next_pairs(w))
    rows = []
    for name, make in (("compress", lambda: S.compress(w, "lz78")), ("cut", lambda: S.x_partition(w, 4)), ("repository", lambda: repo.symbols(w, 4)), ("blocks", lambda: X.block_distance(p)), ("table", lambda: X.dp_distance(p))):
        start = time.time()
        n = make().count()
        rows.append((name, n, round(time.time() - start, 3)))
    return spark.createDataFrame(rows, "phase string, rows long, seconds double")


def w57_anchors(spark, sf):
    """Anchors and chunks of the event words' cuts, by role: how many segments each kind gives."""
    return S.x_partition(event_words(spark, sf), 4).groupBy("role").agg(F.count("*").alias("segments"), F.sum("len").alias("letters"), F.max("len").alias("longest"))


def w58_thresholded(spark, sf):
    """The built-in with a limit, beyond which it gives -1, on names."""
    return next_pairs(names(spark, sf)).select("pair_id", F.levenshtein("a", "b", 8).cast("long").alias("distance"))


def w59_stream_sessions(spark, sf):
    """Event strings of sessions without a pause of six hours, from the stream."""
    from .streaming import events as E

    return E.run_once(E.session_strings(E.read_events(spark, f"{sf}/events.parquet"), "6 hours")).select("user_id", F.unix_micros("start").alias("start_us"), "text")


def w60_opt_out_of_free_matches(spark, sf):
    """Keeping a letter costs as much as replacing it: the distance is the longer length."""
    s = Scoring(1, 1, 1, 1, "rational", False)
    return whole(X.dp_distance(next_pairs(names(spark, sf)), s))


def w64_bit_vectors(spark, sf):
    """Timelines by bit vectors: the same pairs as by runs."""
    return whole(X.bit_distance(next_pairs(timelines(spark, sf))))


def id_pairs(words: DataFrame) -> DataFrame:
    """(pair_id, a_id, b_id): every string with the one whose id is the next number."""
    b = words.select(F.col("string_id").alias("b_id"))
    return words.select(F.col("string_id").alias("pair_id"), F.col("string_id").alias("a_id"), (F.col("string_id") + 1).alias("b_id")).join(b, "b_id").select("pair_id", "a_id", "b_id")


def w61_folded_days(spark, sf):
    """Each user's daily event strings as pieces, folded in order against a fixed word."""
    from .operators.folds import dist_fold

    e = load(spark, sf, "events", "user_id", "ts", "event_id", "event_type").withColumn("letter", F.upper(F.substring("event_type", 1, 1)))
    e = e.withColumn("day", F.expr("timestampdiff(DAY, timestamp_ntz'2024-01-01 00:00:00', ts)"))
    own = F.struct("ts", "event_id", "letter")
    days = e.groupBy(F.col("user_id").alias("key"), F.col("day").alias("seq")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(own)), lambda x: x["letter"]), "").alias("text"))
    d = dist_fold(days, "VCPCV")
    return d.select(F.col("key").alias("user_id"), "letters", F.col("distance").cast("long").alias("distance"))


def w62_uniform_repository(spark, sf):
    """Tables of the equal-pieces cut of the order-status words, each with the distance of its two pieces."""
    w = kept(status_words(spark, sf))
    r = repo.corners(repo.uniform(id_pairs(w), w, 3))
    return r.select("a_text", "b_text", F.col("distance").cast("long").alias("distance"))


def w63_grid(spark, sf):
    """Blocks and distinct symbol pairs of the equal-pieces grid, from counts of symbols."""
    w = kept(event_words(spark, sf))
    seg = kept(S.x_partition(w, 4, "uniform"))
    return S.grid_partition(seg, seg, id_pairs(w)).select("pair_id", "blocks", F.col("distinct_pairs").alias("distinct_keys"))


FAMILIES = {"fibonacci": range(10, 19), "doubling": range(6, 13), "thue": range(6, 12), "periodic": range(40, 400, 60)}


def w65_bounds_hold(spark, sf):
    """Work of the two main methods on pairs of generated words against the bounds that they promise: segments within
    3 N / x + 4, merges within the square of the variables, entries read within a constant times blocks x lg x (blocks
    x for elimination), and fewer of them than cells of the plain table from side 32 on."""
    out = None
    for k, (family, ks) in enumerate(FAMILIES.items()):
        w = S.expand(S.words_table(spark, family, list(ks), "ab"))
        order = Window.orderBy("string_id")  # a few generated words
        p = kept(w.select((F.col("string_id") + 1000 * k).alias("pair_id"), F.col("text").alias("a"), F.lead("text").over(order).alias("b")).where("b IS NOT NULL"))
        for method, d in (("rational", X.rational_distance(p, codec="pairs")), ("arbitrary", X.arbitrary_distance(p, Scoring.unit(), "pairs")), ("elimination", X.arbitrary_distance(p.where("length(a) <= 400"), Scoring.unit(), "pairs", how="elimination"))):  # entry by entry: slow
            d = d.withColumn("method", F.lit(method))
            out = d if out is None else out.unionByName(d)
    c = lambda name: F.coalesce(F.col("counters")[name], F.lit(0)).cast("double")
    a_block = F.when(F.col("method") == "elimination", 64 * (c("x") + 1)).otherwise(64 * (c("x") + 1) * F.log2(c("x") + 1))
    promised = {"segments_ok": c("segments") <= 3 * c("letters") / c("x") + 4, "merges_ok": c("merges") <= c("variables") * c("variables"), "reads_ok": c("probes") <= c("blocks") * a_block, "below_cells": (c("x") < 32) | (c("probes") < c("cells"))}
    return out.select("pair_id", "method", F.col("distance").cast("long").alias("distance"), c("letters").cast("long").alias("letters"), *[v.alias(k) for k, v in promised.items()])


def w66_routes(spark, sf):
    """Which route the pairs of like-language neighbours, timelines and long generated words take."""
    w = S.expand(S.words_table(spark, "periodic", [50, 90], "abcde"))
    t = {"documents": doc_pairs(spark, sf), "timelines": next_pairs(timelines(spark, sf)), "periodic": w.select(F.col("string_id").alias("pair_id"), F.col("text").alias("a"), F.reverse("text").alias("b"))}
    out = None
    for name, p in t.items():
        d = X.unit_distance(p).groupBy(F.lit(name).alias("pairs"), "route").agg(F.count("*").alias("n"))
        out = d if out is None else out.unionByName(d)
    return out


WORKLOADS = {
    **{f.__name__: f for f in (w01_unit_docs, w02_rational_event_words, w03_arbitrary_benchmark, w04_rational_half_cost, w05_indel_urls, w06_mixed_codecs, w07_state_timelines, w08_quantity_runs, w09_order_status, w10_flags_four_russians, w11_embedding_bits, w12_near_copies, w13_conversation_turns, w14_url_pairs, w15_html_pages, w16_fibonacci, w17_example_word, w18_example_block, w18_example_block_kernel, w19_prefix_table, w19_table_by_folds, w19_table_by_paths)},
    **{f"w20_partition_{p}_{x}": partition_query(x, p) for p, x in (("grammar", 4), ("grammar", 16), ("grammar", 64), ("uniform", 16), ("runs", 1), ("phrases", 1))},
    **{f"w21_round_trip_{c}": round_trip_query(c) for c in ("rle", "lz78", "lzw", "words", "lines", "uniform", "balanced")},
    "w21_round_trip_lz77": round_trip_query("lz77", "benchmark", "item_id"),
    "w21_round_trip_pairs": round_trip_query("pairs", "pages", "page_id", "url"),
    **{f.__name__: f for f in (w22_flag_runs, w23_grammar_sizes, w24_repository_keys, w25_bounds, w25_best_side, w26_cost_axioms, w26_triangles, w27_propagation, w28_merging, w29_side_sweep, w29_side_work, w30_variants_agree, w31_similarity_join, w32_nearest, w33_contained, w34_classes, w35_quality_by_distance, w35_distance_cube, w36_stream_running, w37_stream_windows, w38_shared_repository, w39_grammar_against_text, w40_lz78_phrases, w41_quadratic, w42_grammar_rules, w43_valid_rules, w44_corpus_pairs, w44_neighbour_counts, w45_substrings, w46_grammar_algebra, w47_fingerprints, w48_shared_variables, w49_border_values, w50_giant_pair, w51_banded, w52_sql_functions, w53_windows_of_braids, w54_token_dictionary, w55_work_by_variant, w56_phase_seconds, w57_anchors, w58_thresholded, w59_stream_sessions, w60_opt_out_of_free_matches, w61_folded_days, w62_uniform_repository, w63_grid, w64_bit_vectors, w65_bounds_hold, w66_routes)},
}
