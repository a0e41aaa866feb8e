"""SimHash near-duplicates through a Gray-order hierarchical index.

Fingerprints: 64 bits, each set if it is set in over half of the hashes of a text's word shingles (repeats count).
Two fingerprints link at max_bits or fewer differing bits; a class is a connected component.

How links are found without all pairs. Equal fingerprints are merged first (one row with a count, whatever the
group's size). Cut 64 bits into max_bits + 2 bands: two fingerprints within max_bits agree on at least two whole
bands, so each goes under C(max_bits + 2, 2) keys. Rows with one key are sorted by Gray rank, where neighbours
share long patterns, and a hierarchy is laid over them: a node keeps the mask of bits on which all its
fingerprints agree and their values. Pairs of nodes are walked from the root; differences on shared masked bits
only grow downwards, so a pair of nodes over the limit is pruned with everything below it, and so is a pair that
one class already covers. A key with more than hot_rows fingerprints is split exactly: its free bits are banded
again, max_bits + 1 ways, one of which must agree. Only a spanning forest leaves a task, never all links.

Nulls and ties: a null or empty text has fingerprint zero and is linked like any other; ids may repeat; a null id
is never the smallest unless all are null. An empty table gives no rows. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, join_groups, map_batches, table, written

SEED = 42
LANES = np.uint64(0x0101010101010101)
STEPS = np.arange(8, dtype=np.uint64)
AT_ONCE = 100_000  # shingles whose bits are held at a time
ONE_TASK = 1_000_000  # edges whose classes one task finds


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Majority bits of the shingles' XXH64; words are split at ASCII white space, A-Z lower-cased."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    counts, total = np.zeros((8, 8), np.int64), max(len(words) - shingle + 1, 1)  # [k, j]
    digest = xxhash.xxh64_intdigest
    for at in range(0, total, AT_ONCE):
        own = words[at : at + AT_ONCE + shingle - 1]
        joined = b" ".join(own)
        if len(own) <= shingle:
            hashes = [digest(joined, SEED)]
        else:
            ends = [e + k for k, e in enumerate(accumulate(map(len, own)))]
            starts = [0, *[e + 1 for e in ends]]
            hashes = [digest(joined[s:e], SEED) for s, e in zip(starts, ends[shingle - 1 :])]
        h = np.array(hashes, dtype=np.uint64)
        # byte lanes: counter k of byte j counts bit 8 j + k, 255 hashes at a time so that no lane overflows
        bits = (h[:, None] >> STEPS) & LANES
        sums = np.add.reduceat(bits, np.arange(0, len(h), 255), axis=0)
        counts += sums.view(np.uint8).reshape(len(sums), 8, 8).sum(axis=0, dtype=np.int64)
    over = (2 * counts > total).T.reshape(64)  # bit 8 j + k
    return int(np.packbits(over, bitorder="little").view(np.uint64)[0])


def fingerprints(df: DataFrame, id_col: str, text_col: str, shingle: int = 3) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.fromiter((fingerprint(t.as_py(), shingle) for t in b.column(1)), dtype=np.uint64, count=b.num_rows)
            yield batch(id=b.column(0), fp=pa.array(fps.view(np.int64)))

    kind = df.schema[id_col].dataType.simpleString()
    return map_batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), run, f"id {kind}, fp long")


def gray_rank(fp):
    """Place of a 64-bit pattern in the reflected Gray code, as an unsigned number."""
    g = fp.astype(np.uint64).copy()
    for step in (1, 2, 4, 8, 16, 32):
        g ^= g >> np.uint64(step)
    return g


class GrayIndex:
    """A hierarchy over fingerprints in Gray order; links() joins it with itself."""

    def __init__(self, fps: np.ndarray, fan: int = 8):
        self.fps, self.fan, self.masks, self.values = fps, fan, [], []
        ones, zeros = fps, ~fps  # bits that are 1 in all, bits that are 0 in all
        while True:
            cut = np.arange(0, len(ones), fan)
            ones, zeros = np.bitwise_and.reduceat(ones, cut), np.bitwise_and.reduceat(zeros, cut)
            self.masks.append(ones | zeros)
            self.values.append(ones)
            if len(ones) == 1:
                break

    def _children(self, a: np.ndarray, b: np.ndarray, below: int) -> tuple[np.ndarray, np.ndarray]:
        k = np.arange(self.fan)
        x = (a[:, None, None] * self.fan + k[:, None] + 0 * k).reshape(-1)
        y = (b[:, None, None] * self.fan + k + 0 * k[:, None]).reshape(-1)
        ok = (x < below) & (y < below) & (x <= y)
        return x[ok], y[ok]

    def links(self, most: int, chunk: int = 4096) -> np.ndarray:
        """Class label (smallest position) of every fingerprint under links of at most `most` bits."""
        n = len(self.fps)
        label = np.arange(n)
        top = len(self.masks) - 1
        stack = [(top, np.zeros(1, np.int64), np.zeros(1, np.int64))]
        while stack:
            level, a, b = stack.pop()
            if len(a) > chunk:
                stack.append((level, a[chunk:], b[chunk:]))
                a, b = a[:chunk], b[:chunk]
            same = a == b
            m = self.masks[level][a] & self.masks[level][b]
            near = np.bitwise_count((self.values[level][a] ^ self.values[level][b]) & m) <= most
            width = self.fan ** (level + 1)
            lo, hi = self._span(label, width)
            one = (lo[a] == hi[a]) & (lo[b] == hi[b]) & (lo[a] == lo[b])  # one class already: nothing to learn
            a, b, same = a[near & ~one], b[near & ~one], same[near & ~one]
            if not len(a):
                continue
            x, y = self._children(a, b, n if level == 0 else len(self.masks[level - 1]))
            if level:
                far = x != y  # a node's own pairs first: they make the classes that prune the others
                stack += [(level - 1, x[far], y[far]), (level - 1, x[~far], y[~far])]
                continue
            hit = (x < y) & (np.bitwise_count(self.fps[x] ^ self.fps[y]) <= most)
            label = union(label, x[hit], y[hit])
        return label

    @staticmethod
    def _span(label: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        cut = np.arange(0, len(label), width)
        return np.minimum.reduceat(label, cut), np.maximum.reduceat(label, cut)


def union(label: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Merge the classes of linked positions; labels stay the smallest position of the class."""
    if not len(x):
        return label
    label = label.copy()
    while True:
        a, b = label[x], label[y]
        lo, hi = np.minimum(a, b), np.maximum(a, b)
        if (lo == hi).all():
            return label
        np.minimum.at(label, hi, lo)
        while not np.array_equal(nxt := label[label], label):
            label = nxt


def band_key(fp, bands: tuple[tuple[int, int], ...]):
    return [F.shiftrightunsigned(fp, lo).bitwiseAND((1 << n) - 1) for lo, n in bands]


def cut_bits(width: int, parts: int, first: int = 0) -> list[tuple[int, int]]:
    at = [first + width * k // parts for k in range(parts + 1)]
    return [(a, b - a) for a, b in zip(at, at[1:])]


def keyed(fps: DataFrame, most: int) -> DataFrame:
    """Each distinct fingerprint under a key for every choice of two of its max_bits + 2 bands."""
    bands = cut_bits(64, most + 2)
    keys = [F.struct(F.lit(k).alias("pair"), F.concat_ws(",", *band_key(F.col("fp"), two)).alias("bits")) for k, two in enumerate(combinations(bands, 2))]
    return fps.select("fp", F.explode(F.array(*keys)).alias("k")).select("fp", F.col("k.pair").alias("pair"), F.xxhash64("k.pair", "k.bits").alias("key"))


def forest(keys: DataFrame, most: int, parts: int) -> DataFrame:
    """Edges (a, b), b the first of its class in a key's Gray order, from the index over each key's rows."""

    def of(key: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        size = np.diff(np.r_[start, len(key)])
        a, b = [], []
        for s, n in zip(start[size > 1], size[size > 1]):
            own = np.unique(fp[s : s + n])  # a key is a hash: rows of another key that meets it do no harm
            own = own[np.argsort(gray_rank(own))]
            label = GrayIndex(own).links(most)
            own_hit = np.flatnonzero(label != np.arange(len(own)))
            a.append(own[own_hit])
            b.append(own[label[own_hit]])
        none = np.zeros(0, np.uint64)
        return np.concatenate([none, *a]), np.concatenate([none, *b])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_k, keep_f = np.zeros(0, np.int64), np.zeros(0, np.uint64)
        for rb in batches:
            k = np.concatenate([keep_k, rb.column(0).to_numpy()])
            f = np.concatenate([keep_f, rb.column(1).to_numpy().view(np.uint64)])
            cut = int(np.searchsorted(k, k[-1])) if len(k) else 0  # the last key may go on in the next batch
            a, b = of(k[:cut], f[:cut])
            keep_k, keep_f = k[cut:], f[cut:]
            yield batch(a=pa.array(a.view(np.int64)), b=pa.array(b.view(np.int64)))
        a, b = of(keep_k, keep_f)
        yield batch(a=pa.array(a.view(np.int64)), b=pa.array(b.view(np.int64)))

    dealt = keys.select("key", "fp").repartition(parts, "key").sortWithinPartitions("key")
    return map_batches(dealt, run, "a long, b long").distinct()


def near_edges(fps: DataFrame, total: int, most: int = 2, hot_rows: int = 100_000) -> DataFrame:
    keys = written(keyed(fps, most))
    hot = written(keys.groupBy("pair", "key").count().where(F.col("count") > hot_rows))
    if hot.isEmpty():
        plain = keys
    else:
        plain = keys.join(hot, ["pair", "key"], "left_anti")
        bands = cut_bits(64, most + 2)
        cases = F.lit(None).cast("long")
        for k, two in enumerate(combinations(bands, 2)):
            free = [x for x in bands if x not in two]
            subs = [y for lo, n in free for y in cut_bits(n, -(-(most + 1) // len(free)), lo)]
            subkey = F.array(*[F.xxhash64("pair", "key", F.lit(j), *band_key(F.col("fp"), (s,))) for j, s in enumerate(subs)])
            cases = F.when(F.col("pair") == k, subkey).otherwise(cases) if k else F.when(F.col("pair") == k, subkey)
        again = keys.join(hot, ["pair", "key"], "left_semi").select("fp", "pair", F.explode(cases).alias("key"))
        plain = plain.select("fp", "pair", "key").unionByName(again)
    parts = max(int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions")), total // 2_000_000)
    return written(forest(plain, most, parts))


def in_one_task(edges: DataFrame) -> DataFrame:
    """components of edges that one task holds."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.zeros((0, 2), np.int64), *[np.stack([c.to_numpy() for c in b.columns], axis=1) for b in batches]]
        v, at = np.unique(np.concatenate(held), return_inverse=True)
        x, y = at.reshape(-1, 2).T
        root = v[union(np.arange(len(v)), x, y)]
        far = v != root
        yield batch(v=pa.array(v[far]), root=pa.array(root[far]))

    return written(map_batches(edges.select("a", "b").coalesce(1), run, "v long, root long"))


def components(edges: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """(v, root) for every vertex of the edges (a, b) that isn't the least of its class: the large-star and small-star
    rounds of label contraction. Up to one_task edges go to one task: a round is some ten jobs, and what the driver
    keeps for each is more than so few edges."""
    flat = F.when(F.col("a") > F.col("b"), F.struct("a", "b")).otherwise(F.struct(F.col("b").alias("a"), F.col("a").alias("b")))
    cur = written(edges.where("a != b").select(flat.alias("e")).select("e.a", "e.b").distinct())
    state = None
    while True:
        n, mark = cur.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first()
        if n and state is None and n <= one_task:
            return in_one_task(cur)
        if n == 0 or (n, mark) == state:
            return cur.select(F.col("a").alias("v"), F.col("b").alias("root"))
        state = (n, mark)
        both = cur.unionByName(cur.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = written(both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count("*").alias("n")))
        large = join_groups(both, least, "a", "n", 2 * n).where("b > a AND b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = written(large.distinct())
        least = written(large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")))
        small = join_groups(large, least, "a", "n", n).where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        cur = written(small.unionByName(least.select("a", F.col("m").alias("b"))).distinct())


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, max_bits: int = 2, hot_rows: int = 100_000) -> DataFrame:
    """One row per document: id, fingerprint (16 hex digits), component_id (the smallest id of its class)."""
    rows = written(fingerprints(df, id_col, text_col, shingle))
    fps = written(rows.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("n")))
    total = rows.count()
    roots = components(near_edges(fps.select("fp"), total, max_bits, hot_rows))
    of = fps.join(roots, fps.fp == roots.v, "left").select("fp", "least", "n", F.coalesce("root", "fp").alias("root"))
    of = written(of)
    linked = of.where("fp != root").select("root").distinct()
    mins = of.join(linked, "root", "left_semi").groupBy("root").agg(F.min("least").alias("component_id"))
    of = written(of.join(mins, "root", "left").select("fp", "n", F.coalesce("component_id", "least").alias("component_id")))
    out = join_groups(rows, of, "fp", "n", total)
    return out.select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op1_simhash_gray(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
