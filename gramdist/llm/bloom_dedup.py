"""Exact dedup: two-pass Bloom filtering finds possibly repeated hashes; only those rows shuffle.

Pass 1 counts cells, one a row: the leading bits of the text's hash, some 5 more than the number of rows has (a whole
number of four bytes up to 67 million rows, of eight beyond). Cells that two rows hit go into a Bloom filter, two bits
a cell in one 64-bit word; it is written once and broadcast. Pass 2 probes every row: a row whose bits aren't set is
certainly unique and goes straight through; only the rest is grouped by SHA-256. False positives cost a shuffle, never
a result. The filter has BITS bits a repeated cell and at most MAX_WORDS words (512 MB), whatever the table's size;
at that size it still lets nine of ten unique rows pass beside 800 million repeated hashes.

Nulls and ties: a null text equals the empty one; a null id is smaller than any other; where several rows share
the kept id and text, one of them stays. An empty table gives no rows. Input columns named like an output column
are replaced. Texts are hashed whole, whatever their length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import boxed, join_groups, table, unboxed, without, written

BITS = 16  # of the filter for each hash in it
MAX_WORDS = 1 << 26
SPAN = 64  # words in a row of the broadcast filter
MADE = ("keep_id", "group_size", "kept", "text_sha256")


def cell(rows: int, h: Column) -> Column:
    """The leading bits of a hash: among them a row meets another by chance once in 32 rows or less."""
    bits = min(62, max(rows, 1).bit_length() + 5)
    return F.shiftrightunsigned(h, 64 - bits).cast("int" if bits < 32 else "long")


def mask(h: Column) -> Column:
    """Two bits of a word, from the hash's leading bits."""
    one = lambda by: F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(h, by).bitwiseAND(63).cast("int"))
    return one(58).bitwiseOR(one(52))


def filter_of(hashes: DataFrame, max_words: int = MAX_WORDS) -> tuple[DataFrame, int]:
    """A Bloom filter of the column _h (written, without repeats): rows (span, words) and its number of words."""
    n = hashes.count()
    words = min(max_words, 1 << max(10, (n * BITS // 64).bit_length()))
    bits = hashes.groupBy(F.col("_h").bitwiseAND(words - 1).alias("word")).agg(F.bit_or(mask(F.col("_h"))).alias("bits"))
    spans = bits.groupBy(F.shiftright("word", 6).alias("_span")).agg(F.map_from_entries(F.collect_list(F.struct(F.col("word").bitwiseAND(SPAN - 1).cast("int").alias("k"), "bits"))).alias("m"))
    return written(spans.select("_span", F.expr(f"transform(sequence(0, {SPAN - 1}), k -> coalesce(m[k], 0L))").alias("_words"))), words


def flagged(rows: DataFrame, bloom: tuple[DataFrame, int]) -> DataFrame:
    """rows with _maybe: the bits of their hash _h are in the filter, which is broadcast."""
    spans, words = bloom
    word = F.col("_h").bitwiseAND(words - 1)
    rows = rows.withColumn("_at", F.shiftright(word, 6)).join(F.broadcast(spans), F.col("_at") == F.col("_span"), "left")
    held = F.coalesce(F.element_at("_words", word.bitwiseAND(SPAN - 1).cast("int") + 1), F.lit(0).cast("long"))
    own = mask(F.col("_h"))
    return rows.withColumn("_maybe", held.bitwiseAND(own) == own).drop("_at", "_span", "_words")


def without_ids(df: DataFrame, gone: DataFrame, id_col: str = "doc_id", max_words: int = MAX_WORDS) -> DataFrame:
    """df without the rows whose id is in gone (a table of one column of that name, without repeats), columns unchanged.
    A filter of the ids lets all other rows pass; only rows that it flags are shuffled for the exact test. A null id
    stays."""
    bloom = filter_of(gone.where(F.col(id_col).isNotNull()).select(F.xxhash64(id_col).alias("_h")), max_words)
    rows = flagged(df.select(boxed(df), F.col(id_col).alias("_id"), F.xxhash64(id_col).alias("_h")), bloom)
    exact = rows.where("_maybe").join(gone.select(F.col(id_col).alias("_id")), "_id", "left_anti")
    return exact.select("_row").unionByName(rows.where("NOT _maybe").select("_row")).select("_row.*")


def exact_dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", columns: list[str] | None = None, max_words: int = MAX_WORDS) -> DataFrame:
    """Every row of df (its columns, or those named) with keep_id, group_size, kept and text_sha256; of equal texts
    the row with the largest id stays."""
    total = df.count()
    columns = df.columns if columns is None else columns
    text = F.coalesce(F.col(text_col), F.lit(""))
    cells = cell(total, F.xxhash64(text))
    again = written(df.select(cells.alias("_c")).groupBy("_c").count().where("count >= 2").select(F.xxhash64("_c").alias("_h")))
    bloom = filter_of(again, max_words)
    rows = flagged(df.select(boxed(df, columns), F.col(id_col).alias("_id"), text.alias("_text"), F.xxhash64(cells).alias("_h")), bloom).withColumn("text_sha256", F.sha2("_text", 256)).drop("_text", "_h")
    maybe, unique = rows.where("_maybe").drop("_maybe"), rows.where("NOT _maybe").drop("_maybe")
    ident = F.col("_id")
    # written, so that the number that tells repeated rows apart is the same wherever it is read
    maybe = written(maybe.withColumn("_uid", F.monotonically_increasing_id()))
    groups = maybe.groupBy("text_sha256").agg(F.max(F.struct(ident.alias("id"), F.col("_uid").alias("uid"))).alias("_keep"), F.count("*").alias("group_size"))
    groups = written(groups)
    judged = join_groups(maybe, groups, "text_sha256", "group_size", total)
    judged = judged.withColumns({"keep_id": F.col("_keep.id"), "kept": F.col("_keep.uid") == F.col("_uid")})
    unique = unique.withColumns({"keep_id": ident, "group_size": F.lit(1).cast("long"), "kept": F.lit(True)})
    out = [*unboxed(without(columns, *MADE)), *MADE]
    return judged.select(*out).unionByName(unique.select(*out))


def distinct_texts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows that stay, with exactly the columns of df, whatever their names."""
    inner = df.select(boxed(df))
    return exact_dedup(inner, f"_row.`{id_col}`", f"_row.`{text_col}`").where("kept").select("_row.*")


def op9_bloom_dedup(spark, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"), columns=["doc_id"]).select("doc_id", *MADE)


ORACLE = """
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))
"""
