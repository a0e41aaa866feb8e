"""Quality rules by compression bands: zstandard ratios over a whole document and over fixed chunks.

ratio = compressed bytes / bytes. A document is rejected when its ratio, or the ratio of a large enough share of
its chunks, lies outside the band for its length: below, it repeats itself; above, it is not language. Short
texts compress badly whatever they say, so bands are set by length.

Nulls and ties: a null text is an empty one: no words, failed by the base rule, ratio null. Repeated rows are
judged each; a null id is carried. An empty table gives no rows. Other columns are not read. Texts are read whole.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, map_batches, table

SYMBOLS = "#*$%&|<>"
# Least ratios (bytes below which they hold), set wide of what prose in any language shows.
LEAST = ((256, 0.50), (1024, 0.46), (4096, 0.42), (16384, 0.395), (65536, 0.37), (1 << 62, 0.35))
# Most ratios at byte sizes, straight in the logarithm between: above texts of good label cut to that size (400 of
# sf0.1), below random base64 from 128 bytes, random small letters from 1024 and random hex from 2048 (in words of 8).
MOST_AT = (64, 128, 256, 512, 768, 1024, 1536, 2048, 3072, 4096, 8192, 16384)
MOST = (1.30, 0.985, 0.80, 0.72, 0.655, 0.61, 0.56, 0.527, 0.511, 0.505, 0.50, 0.49)
CHUNK = 4096
CHUNK_LEAST = 0.38
BAD_CHUNKS = 0.1  # a document fails when more than this share of its chunks is outside
LEVEL = 3


def long_windows(words: list[bytes], width: int) -> np.ndarray:
    """A number for each window, equal for equal ones: windows grow by a word at a time, in eight bytes each."""
    known: dict[bytes, int] = {}
    one = np.fromiter((known.setdefault(w, len(known)) for w in words), np.int64, len(words))
    out = one
    for k in range(1, width):
        out = np.unique(out[: len(one) - k] * len(known) + one[k:], return_inverse=True)[1]
    return out


def repeated_words(words: list[bytes], width: int = 5, long: int = 100_000) -> int:
    """Words that lie in a window of `width` words found twice or more."""
    if len(words) > long:
        of, n = np.unique(long_windows(words, width), return_inverse=True, return_counts=True)[1:]
        step = np.zeros(len(words) + 1, np.int64)
        at = np.flatnonzero(n[of] > 1)
        step[at] += 1
        step[at + width] -= 1
        return int((np.cumsum(step[:-1]) > 0).sum())
    windows = list(zip(*[words[k:] for k in range(width)]))
    if len(set(windows)) == len(windows):
        return 0
    seen = Counter(windows)
    step = [0] * (len(words) + 1)
    for k, w in enumerate(windows):
        if seen[w] > 1:
            step[k] += 1
            step[k + width] -= 1
    return sum(x > 0 for x in accumulate(step[:-1]))


def base_measures(text: str) -> tuple[int, int, int, int, int]:
    raw = text.encode()
    words = raw.split()  # bytes: ASCII white space only
    lines = [x for x in raw.split(b"\n") if x.strip()]
    blanks = sum(map(text.count, "\x20\x09\x0a\x0b\x0c\x0d"))
    return len(words), len(text) - blanks, sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)), repeated_words(words)


def fits(size: int, ratio: float, least: float | None = None) -> bool:
    """The ratio lies in the band for its bytes; under 64 bytes the frame outweighs the text, so nothing is too much."""
    low = next(lo for below, lo in LEAST if size < below) if least is None else least
    return low <= ratio and (size < MOST_AT[0] or ratio <= np.interp(np.log(size), np.log(MOST_AT), MOST))


def compression_measures(raw: bytes, squeeze: zstandard.ZstdCompressor, chunk: int = CHUNK) -> tuple[float | None, int, int]:
    """Ratio of the whole, chunks (the last may be short), chunks outside the band for their length."""
    if not raw:
        return None, 0, 0
    whole = len(squeeze.compress(raw)) / len(raw)
    parts = [raw[k : k + chunk] for k in range(0, len(raw), chunk)]
    return whole, len(parts), sum(not fits(len(x), len(squeeze.compress(x)) / len(x), CHUNK_LEAST if len(x) == CHUNK else None) for x in parts)


def in_bands(size: int, ratio: float | None, chunks: int, bad: int) -> bool:
    return ratio is not None and fits(size, ratio) and bad <= BAD_CHUNKS * chunks


SCHEMA = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, ratio double, n_chunks long, n_bad_chunks long"


def judge(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: the base counts and rule, the compression measures, kept."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze = zstandard.ZstdCompressor(level=LEVEL)
        names = [x.split()[0] for x in SCHEMA.split(", ")]
        for b in batches:
            rows = []
            for value in b.column(1):
                text = value.as_py() or ""
                n, chars, symbols, dups, repeats = base_measures(text)
                failed = n < 10 or 100 * repeats > 20 * n
                raw = text.encode()
                ratio, chunks, bad = compression_measures(raw, squeeze)
                rows.append((n, chars, symbols, dups, repeats, failed, not failed and in_bands(len(raw), ratio, chunks, bad), ratio, chunks, bad))
            cols = dict(zip(names, map(list, zip(*rows)))) if rows else {k: [] for k in names}
            kinds = {"base_failed": pa.bool_(), "kept": pa.bool_(), "ratio": pa.float64()}
            yield batch(id=b.column(0), **{k: pa.array(cols[k], kinds.get(k, pa.int64())) for k in names})

    kind = df.schema[id_col].dataType.simpleString()
    return map_batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), run, f"id {kind}, {SCHEMA}").withColumnRenamed("id", id_col)


def op4_compression_bands(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"))
