from __future__ import annotations

import pytest

DOC = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in any column, empty and long texts, ties and repeated rows, extra columns with clashing names."""
    long_text = " ".join(f"w{k % 977}x{k % 13}" for k in range(60_000))
    rows = [
        (1, "the quick brown fox jumps over the lazy dog and runs away", "en", "a"),
        (2, "the quick brown fox jumps over the lazy dog and runs away", "en", "a"),
        (2, "the quick brown fox jumps over the lazy dog and runs away", "en", "a"),
        (3, None, None, None),
        (4, "", "en", "b"),
        (5, " \t\n ", None, "b"),
        (None, "no id but a text of its own here", "en", None),
        (None, None, None, None),
        (6, long_text, "xx", "c"),
        (7, "Ünïcode ßtraße   nbsp sep 𝄞 <|im_end|> \\<|x|>", "de", "c"),
        (8, "one", "en", "c"),
        (9, "one\ntwo\none\ntwo\none", "en", None),
    ]
    made = [(*r, len(r[1] or ""), "extra", 1, True, 0.5, "h", 3) for r in rows]
    return spark.createDataFrame(made, DOC + ", fp string, size int, kept boolean, score double, _h string, shard int").repartition(3)


@pytest.fixture(scope="session")
def none(odd):
    return odd.limit(0)


@pytest.fixture(scope="session")
def documents(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"
