"""The workloads' results in plain SQL."""

from __future__ import annotations

from .plans.planner import BOUNDS
from .workloads import SLOTS

# levenshtein counts bytes there, so letters beyond ASCII are renamed one to one to control characters.
WIDE = "ÄÇÈÉÊÍÑÓÖÜßäçèéêíñóöü"
NARROW = "||".join(f"chr({k})" for k in [*range(1, 9), 11, 12, *range(14, 14 + len(WIDE) - 10)])


def narrow(c: str) -> str:
    return f"translate({c}, '{WIDE}', {NARROW})"


def lev(a: str, b: str) -> str:
    return f"CAST(levenshtein({narrow(a)}, {narrow(b)}) AS BIGINT)"


EVENTS = "SELECT user_id AS string_id, string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id) AS text FROM events GROUP BY user_id"
TIMELINES = f"""
SELECT user_id AS string_id, string_agg(repeat(letter, CAST(n AS BIGINT)), '' ORDER BY slot) AS text FROM (
  SELECT user_id, slot, letter, coalesce(lead(slot) OVER (PARTITION BY user_id ORDER BY slot), {SLOTS}) - slot AS n FROM (
    SELECT user_id, least(CAST(floor(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 600) AS BIGINT), {SLOTS - 1}) AS slot,
           arg_max(upper(substr(event_type, 1, 1)), (ts, event_id)) AS letter
    FROM events GROUP BY 1, 2)) GROUP BY 1"""
FLAGS = "SELECT l_suppkey AS string_id, string_agg(l_returnflag, '' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_returnflag) AS text FROM lineitem GROUP BY 1"
QUANTITY = "SELECT l_partkey AS string_id, string_agg(repeat(l_returnflag, CAST(l_quantity AS BIGINT)), '' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_suppkey, l_quantity, l_returnflag) AS text FROM lineitem GROUP BY 1"
STATUS = "SELECT o_custkey AS string_id, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey, o_orderstatus) AS text FROM orders GROUP BY 1"
NAMES = "SELECT row_number() OVER (ORDER BY p_name) - 1 AS string_id, p_name AS text FROM (SELECT DISTINCT p_name FROM part WHERE p_name IS NOT NULL)"
SUPPLIER_ENDS = "SELECT CAST(s_suppkey AS BIGINT) AS string_id, right(s_name, 4) AS text FROM supplier"
BENCH = "SELECT item_id AS string_id, text FROM benchmark"
URLS = "SELECT page_id AS string_id, url AS text FROM pages"
HTML = "SELECT page_id AS string_id, html AS text FROM pages"
NEXT = "SELECT x.string_id AS pair_id, x.text AS a, y.text AS b FROM s x JOIN s y ON y.string_id = x.string_id + 1"
STATUS_PAIRS = f"""SELECT * FROM (SELECT string_id AS pair_id, text AS a, lead(text) OVER (PARTITION BY c_nationkey, c_mktsegment ORDER BY string_id) AS b
FROM ({STATUS}) JOIN customer ON string_id = c_custkey) WHERE b IS NOT NULL"""
DOC_PAIRS = "SELECT x.doc_id AS pair_id, x.lang, x.source, x.text AS a, y.text AS b FROM documents x JOIN documents y ON y.doc_id = x.doc_id + 1 AND x.lang = y.lang"
WORDS = "string_split(trim(regexp_replace(text, '[ \\t\\n\\x0B\\f\\r]+', ' ', 'g'), ' '), ' ')"
COPIES = f"""
SELECT DISTINCT a_id || '-' || b_id AS pair_id, a_id, x.text AS a, y.text AS b FROM (
  SELECT doc_id AS a_id, lead(doc_id) OVER (PARTITION BY k, key ORDER BY doc_id) AS b_id FROM (
    SELECT doc_id, k, list_min(list_transform(m, lambda h: substr(h, 1 + 10 * k, 10))) AS key FROM (
      SELECT doc_id, list_transform(range(1, greatest(len(w) - 4, 1) + 1), lambda i: md5(array_to_string(w[i : i + 4], ' '))) AS m
      FROM (SELECT doc_id, {WORDS} AS w FROM documents WHERE text IS NOT NULL)), range(3) AS t(k)))
JOIN documents x ON x.doc_id = a_id JOIN documents y ON y.doc_id = b_id"""


def next_unit(strings: str) -> str:
    return f"WITH s AS ({strings}), p AS ({NEXT}) SELECT pair_id, {lev('a', 'b')} AS distance FROM p"


def weighted(pairs: str, sub: str, gap: str, out: str = "v") -> str:
    """The prefix table a row at a time as lists; the chain within a row is a running minimum less the gaps so far."""
    return f"""
WITH RECURSIVE {pairs},
t AS (
  SELECT pair_id, a, b, 0 AS i, [CAST(j * {gap} AS DOUBLE) FOR j IN range(0, length(b) + 1)] AS r FROM p
  UNION ALL
  SELECT pair_id, a, b, i + 1, (
    SELECT list(least_so_far + j * {gap} ORDER BY j) FROM (
      SELECT j, min(c - j * {gap}) OVER (ORDER BY j ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS least_so_far FROM (
        SELECT j, CASE WHEN j = 0 THEN r[1] + {gap} ELSE least(r[j + 1] + {gap}, r[j] + {sub}) END AS c
        FROM unnest(range(0, length(b) + 1)) AS u(j))))
  FROM t WHERE i < length(a))
SELECT pair_id, {out.replace('v', 'r[length(b) + 1]')} AS distance FROM t WHERE i = length(a)"""


X, Y = "substr(a, i + 1, 1)", "substr(b, j, 1)"
VOWEL = "strpos('aeiouAEIOU', {0}) > 0"
LETTER = "strpos('abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ', {0}) > 0"
CLASS_SUB = f"""CASE WHEN {X} = {Y} THEN 0 WHEN NOT ({LETTER.format(X)}) OR NOT ({LETTER.format(Y)}) THEN 2
WHEN ({VOWEL.format(X)}) <> ({VOWEL.format(Y)}) THEN 3 WHEN {VOWEL.format(X)} THEN 1 ELSE 2 END"""

FIB = """RECURSIVE l AS (SELECT row_number() OVER (ORDER BY r_name) - 1 AS n, substr(r_name, 1, 1) AS x, substr(r_name, 2, 1) AS y FROM region),
f AS (SELECT n, 1 AS k, y AS v, x AS w FROM l UNION ALL SELECT n, k + 1, w, w || v FROM f WHERE k < 18),
s AS (SELECT k + 100 * n AS string_id, v AS text FROM f WHERE k BETWEEN 5 AND 18)"""


def lg(c: str) -> str:
    return f"log2(1.0 + {c})"


BOUND_SQL = {
    "block_rational": f"n * n * x * {lg('x')} + N_ * N_ * {lg('x')} / x",
    "block_arbitrary": "n * n * x * x + N_ * N_ / x",
    "repository_rational": f"n * n * x * {lg('x')}",
    "repository_arbitrary": "n * n * x * x",
    "sweep_rational": f"N_ * N_ * {lg('x')} / x",
    "sweep_arbitrary": "N_ * N_ / x",
    "best_rational": f"n * N_ * {lg('N_ / n')}",
    "best_arbitrary": "pow(n, 2.0 / 3) * pow(N_, 4.0 / 3)",
    "quadratic": "N_ * N_",
    "four_russians": f"N_ * N_ / {lg('N_')}",
    "four_russians_word": f"N_ * N_ / ({lg('N_')} * {lg('N_')})",
    "runs_or_phrases": "n * N_",
    "grammar_slow_merge": "n * pow(N_, 1.5)",
    "grammar_fast_merge": f"n * N_ * {lg('N_')}",
    "grammar_strict_partition": "pow(n, 1.34) * pow(N_, 1.34)",
}
LENGTHS = f"SELECT string_id, CAST(1 + len([1 FOR i IN range(2, length(text) + 1) IF substr(text, i, 1) <> substr(text, i - 1, 1)]) AS BIGINT) AS n0, CAST(length(text) AS BIGINT) AS len FROM ({TIMELINES})"


def bounds_sql() -> str:
    cols = ", ".join(f"round(log2({BOUND_SQL[k]}), 6) AS {k}" for k in BOUNDS)
    return f"""WITH t AS (SELECT string_id, n0, len, CAST(n0 AS DOUBLE) AS n, CAST(len AS DOUBLE) AS N_,
least(greatest(ceil(CAST(len AS DOUBLE) / n0), 1), len) AS x FROM ({LENGTHS}))
SELECT string_id, n0 AS variables, len AS letters, CAST(x AS BIGINT) AS x, {cols} FROM t"""


def text_sql(table: str, id_col: str, text_col: str = "text") -> str:
    return f"SELECT {id_col} AS string_id, CAST(length({text_col}) AS BIGINT) AS letters, md5({text_col}) AS text_md5 FROM {table} WHERE {text_col} <> ''"


PART = "SELECT doc_id, CAST(length(text) AS BIGINT) AS covered, true AS short_enough, true AS one_text, md5(text) AS joined_md5 FROM documents WHERE text <> ''"
BLOCK = """SELECT i, j, CAST(levenshtein(substr(a, r0 + 1, r1 - r0), substr(b, c0 + 1, c1 - c0)) AS BIGINT) AS w{0} FROM (
SELECT *, greatest(p - i, 0) AS r0, greatest(i - p, 0) AS c0, p - greatest(j - q, 0) AS r1, least(j, q) AS c1 FROM (
  SELECT *, unnest(range(0, p + q + 1)) AS j FROM (SELECT *, unnest(range(0, p + q + 1)) AS i FROM (SELECT *, length(a) AS p, length(b) AS q FROM ({1}))))
WHERE j <= q + i AND i <= p + j)"""
NAME_PAIRS = f"WITH s AS ({NAMES}), p AS ({NEXT})"
CLOSE = f"SELECT x.text AS a, y.text AS b, CAST(levenshtein(x.text, y.text) AS BIGINT) AS distance FROM ({NAMES}) x JOIN ({NAMES}) y ON x.text < y.text WHERE levenshtein(x.text, y.text) <= 2"

ORACLES = {
    "w01_unit_docs": f"WITH p AS ({DOC_PAIRS}) SELECT pair_id, {lev('a', 'b')} AS distance FROM p",
    "w02_rational_event_words": next_unit(EVENTS),
    "w03_arbitrary_benchmark": weighted(f"s AS ({BENCH}), p AS ({NEXT})", CLASS_SUB, "2", "round(v, 6)"),
    "w04_rational_half_cost": weighted(f"s AS ({NAMES}), p AS ({NEXT})", f"CASE WHEN {X} = {Y} THEN 0 ELSE 1.5 END", "1", "round(v, 6)"),
    "w05_indel_urls": weighted(f"s AS ({URLS}), p AS ({NEXT})", f"CASE WHEN {X} = {Y} THEN 0 ELSE 2 END", "1", "CAST(v AS BIGINT)"),
    "w06_mixed_codecs": next_unit(EVENTS),
    "w07_state_timelines": next_unit(TIMELINES),
    "w08_quantity_runs": next_unit(QUANTITY),
    "w09_order_status": f"SELECT pair_id, {lev('a', 'b')} AS distance FROM ({STATUS_PAIRS})",
    "w10_flags_four_russians": next_unit(FLAGS),
    "w11_embedding_bits": f"""WITH s AS (SELECT vec_id AS string_id, label, array_to_string([CASE WHEN x >= 0 THEN '1' ELSE '0' END FOR x IN embedding], '') AS text FROM embeddings),
p AS (SELECT string_id AS pair_id, text AS a, lead(text) OVER (PARTITION BY label ORDER BY string_id) AS b FROM s) SELECT pair_id, {lev('a', 'b')} AS distance FROM p WHERE b IS NOT NULL""",
    "w12_near_copies": f"SELECT pair_id, {lev('a', 'b')} AS distance FROM ({COPIES})",
    "w13_conversation_turns": f"SELECT x.conv_id * 1000 + x.turn AS pair_id, {lev('x.text', 'y.text')} AS distance FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn + 2 AND x.role = y.role",
    "w14_url_pairs": next_unit(URLS),
    "w15_html_pages": next_unit(HTML),
    "w16_fibonacci": f"WITH {FIB}, p AS ({NEXT}) SELECT CAST(pair_id AS BIGINT) AS pair_id, CAST(levenshtein(a, b) AS BIGINT) AS distance FROM p",
    "w17_example_word": "WITH RECURSIVE f AS (SELECT s_suppkey, CAST(1 AS BIGINT) AS k, right(s_name, 1) AS v, substr(right(s_name, 2), 1, 1) AS w FROM supplier WHERE length(s_name) >= 2 UNION ALL SELECT s_suppkey, k + 1, w, w || v FROM f WHERE k < 7) SELECT s_suppkey, k, v AS text FROM f",
    "w18_example_block": BLOCK.format("", f"WITH s AS ({SUPPLIER_ENDS}) {NEXT}").replace("SELECT i, j,", "SELECT pair_id, CAST(i AS INT) AS i, CAST(j AS INT) AS j,"),
    "w19_prefix_table": f"{NAME_PAIRS}, g AS (SELECT *, unnest(range(0, length(b) + 1)) AS j FROM (SELECT *, unnest(range(0, length(a) + 1)) AS i FROM p)) SELECT pair_id, i, j, CAST(levenshtein(substr(a, 1, i), substr(b, 1, j)) AS BIGINT) AS value FROM g",
    "w19_table_by_folds": next_unit(NAMES),
    "w19_table_by_paths": next_unit(NAMES),
    **{k: PART for k in ("w20_partition_grammar_4", "w20_partition_grammar_16", "w20_partition_grammar_64", "w20_partition_uniform_16", "w20_partition_runs_1", "w20_partition_phrases_1")},
    **{f"w21_round_trip_{c}": text_sql("documents", "doc_id") for c in ("rle", "lz78", "lzw", "words", "lines", "uniform", "balanced")},
    "w21_round_trip_lz77": text_sql("benchmark", "item_id"),
    "w21_round_trip_pairs": text_sql("pages", "page_id", "url"),
    "w22_flag_runs": """WITH d AS (SELECT l_suppkey, l_returnflag, row_number() OVER w AS k, CASE WHEN l_returnflag IS DISTINCT FROM lag(l_returnflag) OVER w THEN 1 ELSE 0 END AS new
FROM lineitem WINDOW w AS (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey)),
r AS (SELECT *, sum(new) OVER (PARTITION BY l_suppkey ORDER BY k) AS run FROM d)
SELECT l_suppkey, CAST(run AS BIGINT) AS run, l_returnflag, count(*) AS length FROM r GROUP BY ALL""",
    "w24_repository_keys": f"""WITH s AS ({EVENTS}), c AS (SELECT string_id, substr(text, k * 4 + 1, 4) AS sym, count(*) AS n FROM (SELECT *, unnest(range(0, (length(text) - 1) // 4 + 1)) AS k FROM s) GROUP BY 1, 2)
SELECT x.string_id AS pair_id, CAST(sum(x.n * y.n) AS BIGINT) AS blocks, count(*) AS distinct_keys FROM c x JOIN c y ON y.string_id = x.string_id + 1 GROUP BY 1""",
    "w25_bounds": bounds_sql(),
    "w25_best_side": f"""WITH t AS ({LENGTHS}), g AS (SELECT string_id, n0, len, CAST(n0 AS DOUBLE) AS n, CAST(len AS DOUBLE) AS N_, CAST(1 << k AS DOUBLE) AS x FROM (SELECT *, unnest(range(0, CAST(floor(log2(len)) AS BIGINT) + 1)) AS k FROM t)),
c AS (SELECT *, {BOUND_SQL['block_rational']} AS cost FROM g)
SELECT string_id, n0 AS variables, len AS letters, CAST(arg_min(x, [cost, x]) AS BIGINT) AS best_x, round(log2(min(cost)), 6) AS best_cost, CAST(least(greatest(ceil(any_value(N_) / any_value(n)), 1), len) AS BIGINT) AS closed_x FROM c GROUP BY string_id, n0, len""",
    "w26_triangles": f"""WITH n AS ({NAMES}), t AS (SELECT levenshtein(x.text, y.text) AS ab, levenshtein(y.text, z.text) AS bc, levenshtein(x.text, z.text) AS ac
FROM n x JOIN n y ON y.string_id = x.string_id + 1 JOIN n z ON z.string_id = x.string_id + 2)
SELECT count(*) AS triples, CAST(sum(CASE WHEN ac > ab + bc OR ab > ac + bc OR bc > ab + ac THEN 1 ELSE 0 END) AS BIGINT) AS violations, CAST(sum(ac) AS BIGINT) AS letters FROM t""",
    "w27_propagation": f"""WITH s AS ({NAMES}), p AS ({NEXT}), w AS ({BLOCK.format(', pair_id, p', 'SELECT * FROM p')}) SELECT pair_id, j, CAST(min(w + abs(p - i)) AS BIGINT) AS v FROM w GROUP BY pair_id, j""",
    "w28_merging": BLOCK.format(", string_id AS pair_id", f"SELECT string_id, text AS a, 'the quick' AS b FROM ({NAMES})"),
    "w29_side_sweep": f"WITH d AS ({next_unit(EVENTS)}) SELECT pair_id, distance, CAST(x AS BIGINT) AS x FROM d, unnest([1, 2, 4, 8, 16, 32]) AS u(x)",
    "w30_variants_agree": f"SELECT pair_id, CAST(1 AS BIGINT) AS n_values, CAST(24 AS BIGINT) AS n_variants, {lev('a', 'b')} AS distance FROM ({STATUS_PAIRS})",
    "w31_similarity_join": CLOSE,
    "w32_nearest": f"""SELECT * FROM (SELECT query_id, string_id, distance, row_number() OVER (PARTITION BY query_id ORDER BY distance, string_id) AS rank FROM (
SELECT x.item_id AS query_id, y.item_id AS string_id, {lev('x.text', 'y.text')} AS distance FROM benchmark x JOIN benchmark y ON x.item_id <> y.item_id)) WHERE rank <= 3""",
    "w34_classes": f"""WITH RECURSIVE e AS ({CLOSE}), b AS (SELECT a, b FROM e UNION SELECT b, a FROM e), r AS (SELECT a AS name, a AS label FROM b UNION SELECT b.b, r.label FROM r JOIN b ON b.a = r.name)
SELECT name, min(label) AS label FROM r GROUP BY name""",
    "w35_quality_by_distance": f"SELECT quality, toxic, count(*) AS pairs, round(avg({lev('a', 'b')}), 6) AS mean_distance FROM ({COPIES}) LEFT JOIN labels ON doc_id = a_id GROUP BY 1, 2",
    "w35_distance_cube": f"WITH d AS (SELECT lang, source, {lev('a', 'b')} AS d FROM ({DOC_PAIRS})) SELECT lang, source, CAST(grouping(lang, source) AS BIGINT) AS level, count(*) AS pairs, CAST(sum(d) AS BIGINT) AS distance FROM d GROUP BY CUBE (lang, source)",
    "w36_stream_running": f"WITH s AS ({EVENTS}), t AS (SELECT text FROM s ORDER BY string_id LIMIT 1) SELECT string_id AS user_id, CAST(length(s.text) AS BIGINT) AS events, CAST(levenshtein(s.text, t.text) AS BIGINT) AS distance FROM s, t",
    "w38_shared_repository": next_unit(EVENTS),
    "w39_grammar_against_text": next_unit(EVENTS),
    "w40_lz78_phrases": next_unit(EVENTS),
    "w41_quadratic": next_unit(FLAGS),
    "w42_grammar_rules": f"SELECT string_id, CAST(length(text) AS BIGINT) AS letters FROM ({EVENTS})",
}
EVENT_PAIRS = f"WITH s AS ({EVENTS}), p AS ({NEXT})"
ORACLES |= {
    "w26_cost_axioms": """WITH l AS (SELECT DISTINCT x FROM (SELECT unnest(string_split(p_name, '')) AS x FROM part) WHERE x <> ''),
s AS (SELECT l.x AS a, m.x AS b, CASE WHEN l.x = m.x THEN 0 WHEN l.x || m.x IN ('ab', 'bc') THEN 1 WHEN l.x || m.x = 'ac' THEN 5 ELSE 3 END AS c FROM l, l m),
g AS (SELECT x, CASE WHEN x = 'a' THEN 3 ELSE 2 END AS d, 1 AS i FROM l),
v AS (SELECT 'symmetry' AS axiom, abs(s.c - t.c) AS e FROM s JOIN s t ON s.a = t.b AND s.b = t.a WHERE s.a < s.b AND s.c <> t.c
UNION ALL SELECT 'symmetry', abs(d - i) FROM g WHERE d <> i
UNION ALL SELECT 'triangle', s.c - x.c - y.c FROM s JOIN s x ON s.a = x.a JOIN s y ON x.b = y.a AND y.b = s.b WHERE s.c > x.c + y.c)
SELECT axiom, count(*) AS violations, CAST(max(e) AS DOUBLE) AS most FROM v GROUP BY axiom""",
    "w37_stream_windows": """WITH d AS (SELECT user_id, CAST(date_trunc('day', ts) AS DATE) AS d, string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id) AS text FROM events GROUP BY 1, 2)
SELECT user_id, strftime(d, '%Y-%m-%d') AS day, text, CAST(levenshtein(text, 'VCPCV') AS BIGINT) AS distance FROM d
WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)""",
    "w44_corpus_pairs": "SELECT page_id AS string_id, md5(url) AS text_md5 FROM pages WHERE url <> ''",
    "w44_neighbour_counts": f"SELECT substr(text, k, 2) AS pair, count(*) AS n FROM (SELECT text, unnest(range(1, length(text))) AS k FROM ({EVENTS})) GROUP BY 1",
    "w45_substrings": "SELECT doc_id AS string_id, substr(text, 100, 50) AS text FROM documents WHERE text <> ''",
    "w46_grammar_algebra": """SELECT page_id AS string_id, kind, md5(CASE kind WHEN 'reverse' THEN reverse(url) WHEN 'concat' THEN url || url WHEN 'power' THEN repeat(url, 5) ELSE url END) AS text_md5
FROM pages, unnest(['reverse', 'concat', 'power', 'normal']) AS u(kind)""",
    "w47_fingerprints": "SELECT count(DISTINCT text) AS texts FROM documents WHERE text <> ''",
    "w49_border_values": f"{EVENT_PAIRS} SELECT pair_id, CAST(j AS BIGINT) AS col, CAST(levenshtein(a, substr(b, 1, j)) AS BIGINT) AS value FROM (SELECT *, unnest(range(0, length(b) + 1)) AS j FROM p)",
    "w50_giant_pair": """WITH a AS (SELECT string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY event_id) AS a FROM events), b AS (SELECT string_agg(o_orderstatus, '' ORDER BY o_orderkey) AS b FROM orders)
SELECT CAST(length(a) AS BIGINT) AS letters_a, CAST(length(b) AS BIGINT) AS letters_b, CAST(levenshtein(a, b) AS BIGINT) AS distance FROM a, b""",
    "w51_banded": f"{EVENT_PAIRS} SELECT pair_id, CASE WHEN levenshtein(a, b) <= 42 THEN CAST(levenshtein(a, b) AS BIGINT) END AS distance FROM p",
    "w52_sql_functions": f"{NAME_PAIRS} SELECT pair_id, CAST(levenshtein(a, b) AS BIGINT) AS distance, a AS text, 'the quick brown fox' AS cut FROM p",
    "w53_windows_of_braids": f"""{NAME_PAIRS} SELECT pair_id, CAST(min(levenshtein(a, substr(b, i + 1, j - i))) AS BIGINT) AS distance
FROM (SELECT *, unnest(range(i, length(b) + 1)) AS j FROM (SELECT *, unnest(range(0, length(b) + 1)) AS i FROM p)) GROUP BY pair_id""",
    "w54_token_dictionary": "SELECT CAST(length(token) AS BIGINT) AS letters, count(*) AS tokens, CAST(sum(n) AS BIGINT) AS uses FROM (SELECT token, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS token FROM documents) WHERE token <> '' GROUP BY 1) GROUP BY 1",
    "w58_thresholded": f"{NAME_PAIRS} SELECT pair_id, CASE WHEN levenshtein(a, b) <= 8 THEN CAST(levenshtein(a, b) AS BIGINT) ELSE -1 END AS distance FROM p",
    "w60_opt_out_of_free_matches": f"{NAME_PAIRS} SELECT pair_id, CAST(greatest(length(a), length(b)) AS BIGINT) AS distance FROM p",
}
ORACLES["w18_example_block_kernel"] = ORACLES["w18_example_block"]
ORACLES |= {
    "w61_folded_days": f"SELECT string_id AS user_id, CAST(length(text) AS BIGINT) AS letters, CAST(levenshtein(text, 'VCPCV') AS BIGINT) AS distance FROM ({EVENTS})",
    "w62_uniform_repository": f"""WITH s AS ({STATUS}), g AS (SELECT DISTINCT string_id, substr(text, k * 3 + 1, 3) AS t FROM (SELECT *, unnest(range(0, (length(text) - 1) // 3 + 1)) AS k FROM s))
SELECT DISTINCT x.t AS a_text, y.t AS b_text, CAST(levenshtein(x.t, y.t) AS BIGINT) AS distance FROM g x JOIN g y ON y.string_id = x.string_id + 1""",
    "w63_grid": ORACLES["w24_repository_keys"],
}
ORACLES["w59_stream_sessions"] = """
WITH d AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM d)
SELECT user_id, epoch_us(min(ts)) AS start_us, string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id) AS text FROM s GROUP BY user_id, k
HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)"""
ORACLES["w64_bit_vectors"] = ORACLES["w07_state_timelines"]

ORACLES["w65_bounds_hold"] = """
WITH RECURSIVE f AS (SELECT 2 AS k, 'a' AS text, 'b' AS before UNION ALL SELECT k + 1, text || before, text FROM f WHERE k < 18),
w AS (
  SELECT k AS string_id, text, 0 AS family FROM f WHERE k >= 10
  UNION ALL SELECT k, repeat('a', CAST(1 << k AS BIGINT)), 1 FROM range(6, 13) t(k)
  UNION ALL SELECT k, (SELECT string_agg(CASE WHEN bit_count(i) % 2 = 0 THEN 'a' ELSE 'b' END, '' ORDER BY i) FROM range(CAST(1 << k AS BIGINT)) u(i)), 2 FROM range(6, 12) t(k)
  UNION ALL SELECT k, repeat('ab', k), 3 FROM range(40, 400, 60) t(k)),
p AS (SELECT string_id + 1000 * family AS pair_id, text AS a, lead(text) OVER (PARTITION BY family ORDER BY string_id) AS b FROM w)
SELECT pair_id, method, CAST(levenshtein(a, b) AS BIGINT) AS distance, CAST(length(a) + length(b) AS BIGINT) AS letters,
       true AS segments_ok, true AS merges_ok, true AS reads_ok, true AS below_cells
FROM p, (VALUES ('rational'), ('arbitrary'), ('elimination')) m(method) WHERE b IS NOT NULL AND (method <> 'elimination' OR length(a) <= 400)"""
