"""Near copies by exact Jaccard: classes of texts whose sets of five-word shingles agree by four fifths or more.

Words are split at ASCII white space, A-Z lower-cased; a text of fewer words is one shingle, and texts without words
are alike. A class is a connected component of links.

How links are found. First the Gray-order index of simhash.py over the texts' SimHash fingerprints (of these
shingles) proposes a spanning forest of its classes, and what it proposes is verified on whole sets. Links between
fingerprints further apart come from an exact search that only looks between the classes so far, without all pairs
and without loss. Two sets that agree so far share a shingle among the first
fifth (and one) of each, in any one order of shingles; frequent shingles are put last. Rows that share such a
shingle are candidates if sizes, places and parity fingerprints (each bit the parity of the shingles that hash to it,
so differing bits never exceed differing shingles) leave the link possible. Candidates are verified on whole sets, after wider parity
sketches. In
the first rounds a shingle's rows, in a Gray order of their parities, are only tried with a neighbour and a centre,
which joins most of a large class at a linear cost; the last round tries all pairs that are not of one class yet and
whose wider parities, which its rows carry, leave the link possible, so that a large group yields no pair for each two of its rows. A
pair is verified once, and a later round only joins classes.

Nulls and ties: a null text is an empty one; ids may repeat; a null id links others but is never the smallest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bloom_dedup import filter_of, flagged
from .common import batch, driver_gives_back, join_groups, map_batches, written
from .simhash import components, fingerprints, gray_rank, near_edges

U = np.uint64
WIDTH = 5
PART, WHOLE = 4, 5  # linked when 5 * shared >= 4 * all
FREQUENT = 100  # a shingle in more texts goes last
AT_ONCE = 1_000_000
BITS = 3  # between fingerprints that the Gray-order index links
FEW = 50_000  # texts whose numbers are broadcast as they are
WIDE = 1024  # parity bits of a row in the last round
ROWS = "tok long, v long, size int, pos int, fp long"


def mixed(z: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        z = (z ^ (z >> U(30))) * U(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> U(27))) * U(0x94D049BB133111EB)
    return z ^ (z >> U(31))


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Distinct shingle hashes in order."""
    words = (text or "").encode().lower().split()
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), U, len(words))
    n = max(len(words) - width + 1, 1)
    out = np.full(n, min(len(words), width), U)
    for k in range(min(width, len(words))):
        out = mixed(out ^ h[k : k + n]) + U(k)
    return np.unique(out)


def parity(own: np.ndarray) -> int:
    odd = np.bincount((own >> U(58)).astype(np.int64), minlength=64) & 1
    return int(np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)[0])


def frequent(texts: DataFrame) -> np.ndarray:
    """Shingles that many texts hold, rarest first. Counts below 3 in a task's share are left out: they only set an
    order, and any order finds all links."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def flush() -> pa.RecordBatch:
            tok, n = np.unique(np.concatenate([np.zeros(0, U), *held]), return_counts=True)
            return batch(tok=pa.array(tok[n > 2].view(np.int64)), n=pa.array(n[n > 2].astype(np.int64)))

        for b in batches:
            for t in b.column(1):
                held.append(shingles(t.as_py()))
                size += len(held[-1])
                if size >= AT_ONCE:
                    yield flush()
                    held, size = [], 0
        yield flush()

    counts = map_batches(texts, run, "tok long, n long").groupBy("tok").agg(F.sum("n").alias("n")).where(F.col("n") > FREQUENT)
    top = counts.orderBy(F.desc("n"), "tok").limit(AT_ONCE).toPandas()
    return top["tok"].to_numpy(np.int64).view(U)[::-1]


def prefixes(texts: DataFrame, last: np.ndarray) -> DataFrame:
    """The first shingles of every text, those of `last` put after the others in the order given."""
    at = np.argsort(last)
    shared = texts.sparkSession.sparkContext.broadcast((last[at], at))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, rank = shared.value
        for b in batches:
            made = [np.zeros((0, 5), np.int64)]
            for v, t in zip(b.column(0).to_pylist(), b.column(1)):
                own = shingles(t.as_py())
                s = len(own)
                take = s - -(-PART * s // WHOLE) + 1
                order = own
                if len(known):
                    i = np.minimum(np.searchsorted(known, own), len(known) - 1)
                    late = known[i] == own
                    order = np.r_[own[~late], own[late][np.argsort(rank[i[late]])]]
                row = np.empty((take, 5), np.int64)
                row[:, 0], row[:, 1], row[:, 2], row[:, 3], row[:, 4] = order[:take].view(np.int64), v, s, np.arange(take), parity(own)
                made.append(row)
            m = np.concatenate(made)
            yield batch(tok=pa.array(m[:, 0]), v=pa.array(m[:, 1]), size=pa.array(m[:, 2].astype(np.int32)), pos=pa.array(m[:, 3].astype(np.int32)), fp=pa.array(m[:, 4]))

    return map_batches(texts, run, ROWS)


def by_token(rows: DataFrame, of, schema: str) -> DataFrame:
    """of(columns) over all rows of some shingles at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            if not b.num_rows:
                continue
            new = [np.frombuffer(b"".join(c.to_pylist()), U).reshape(len(c), -1) if pa.types.is_binary(c.type) else c.to_numpy() for c in b.columns]
            held = new if held is None else [np.concatenate(x) for x in zip(held, new)]
            cut = int(np.searchsorted(held[0], held[0][-1]))  # the last shingle may go on in the next batch
            if cut:
                yield from of([x[:cut] for x in held])
                held = [x[cut:] for x in held]
        if held is not None:
            yield from of(held)

    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return map_batches(rows.repartition(n, "tok").sortWithinPartitions("tok"), run, schema)


def shared_only(rows: DataFrame) -> DataFrame:
    """Rows whose shingle another text has too, one for each text."""

    def of(x: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        at = np.lexsort((x[1], x[0]))
        x = [c[at] for c in x]
        new = np.r_[True, (x[0][1:] != x[0][:-1]) | (x[1][1:] != x[1][:-1])]
        x = [c[new] for c in x]
        same = x[0][1:] == x[0][:-1]
        hit = np.r_[False, same] | np.r_[same, False]
        yield batch(**{k: pa.array(c[hit]) for k, c in zip(("tok", "v", "size", "pos", "fp"), x)})

    return by_token(rows, of, ROWS)


def undecided(rows: DataFrame) -> DataFrame:
    """Rows of the shingles whose texts aren't of one class."""

    def of(x: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        start = np.flatnonzero(np.r_[True, x[0][1:] != x[0][:-1]])
        several = np.minimum.reduceat(x[5], start) != np.maximum.reduceat(x[5], start)
        keep = np.repeat(several, np.diff(np.r_[start, len(x[0])]))
        yield batch(**{k: pa.array(c[keep]) for k, c in zip(("tok", "v", "size", "pos", "fp", "root"), x)})

    return by_token(rows, of, f"{ROWS}, root long")


def candidates(rows: DataFrame, turn: int, whole: bool) -> DataFrame:
    """Pairs (a, b), a < b, of different classes whose link isn't ruled out: of neighbours in the turn's order, or of
    all rows, which then carry their wide parities."""

    def of(x: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        tok, v, size, pos, fp, root, *wide = x
        rank = (fp ^ tok).view(U)  # another order for every shingle
        by = U(21 * turn % 64)
        rank = gray_rank((rank << by) | (rank >> (U(64) - by)) if by else rank)
        at = np.lexsort((rank, tok))
        wide = [c[at] for c in wide]
        tok, v, size, pos, fp, root = [c[at] for c in (tok, v, size.astype(np.int64), pos.astype(np.int64), fp, root)]
        start = np.flatnonzero(np.r_[True, tok[1:] != tok[:-1]])
        n = np.diff(np.r_[start, len(tok)])
        first, end = np.repeat(start, n), np.repeat(start + n, n)

        def pairs(i: np.ndarray, j: np.ndarray) -> pa.RecordBatch:
            both = size[i] + size[j]
            most = np.minimum(size[i] - pos[i], size[j] - pos[j])  # shared, if this is the first shared shingle
            ok = (root[i] != root[j]) & (WHOLE * np.minimum(size[i], size[j]) >= PART * np.maximum(size[i], size[j]))
            ok &= (PART + WHOLE) * most >= PART * both
            ok &= (PART + WHOLE) * np.bitwise_count((fp[i] ^ fp[j]).view(U)).astype(np.int64) <= (WHOLE - PART) * both
            i, j, both = i[ok], j[ok], both[ok]
            for c in wide:
                ok = (PART + WHOLE) * np.bitwise_count(c[i] ^ c[j]).sum(axis=1, dtype=np.int64) <= (WHOLE - PART) * both
                i, j = i[ok], j[ok]
            a, b = np.minimum(v[i], v[j]), np.maximum(v[i], v[j])
            return batch(a=pa.array(a), b=pa.array(b))

        i = np.arange(len(tok))
        if not whole:
            yield pairs(i[i > first] - 1, i[i > first])
            yield pairs(first[i > first + 1], i[i > first + 1])
            return
        one = np.minimum.reduceat(root, start) == np.maximum.reduceat(root, start)  # one class: nothing to learn
        i, step = i[~np.repeat(one, n)], 1
        while len(i := i[i + step < end[i]]):
            yield pairs(i, i + step)
            step += 1

    return by_token(rows, of, "a long, b long").distinct()


def sketch(own: np.ndarray, m: int = 0) -> np.ndarray:
    """Parity bits of a set, m or two or more a shingle, by the low bits of the hashes: a wider one folds to a narrower."""
    m = m or max(64, 1 << (2 * len(own) - 1).bit_length())
    odd = np.bincount((own & U(m - 1)).astype(np.int64), minlength=m) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little")


def by_sketch(a: np.ndarray, b: np.ndarray, sizes: int) -> bool:
    """False only if the sets can't be linked."""
    while len(a) != len(b):
        if len(a) < len(b):
            a, b = b, a
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    return (PART + WHOLE) * int(np.bitwise_count(a ^ b).sum(dtype=np.int64)) <= (WHOLE - PART) * sizes


def by_set(a: np.ndarray, b: np.ndarray, sizes: int) -> bool:
    shared = len(np.intersect1d(a.view(U), b.view(U), assume_unique=True))
    return WHOLE * shared >= PART * (sizes - shared)


def among(texts: DataFrame, used: DataFrame) -> DataFrame:
    """The texts of used (column v, written, without repeats), and a few others where these are many."""
    if used.count() <= FEW:
        return texts.join(F.broadcast(used.select("v")), "v", "left_semi").select("v", "text")
    return flagged(texts.withColumn("_h", F.col("v")), filter_of(used.select(F.col("v").alias("_h")))).where("_maybe").select("v", "text")


def with_parities(texts: DataFrame, rows: DataFrame) -> DataFrame:
    """rows (written) with the WIDE parity bits of their texts; only of the texts in rows."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield batch(v=b.column(0), wide=pa.array([sketch(shingles(t.as_py()), WIDE).tobytes() for t in b.column(1)], pa.binary()))

    used = written(rows.select("v").distinct())
    return rows.join(written(map_batches(among(texts, used), made, "v long, wide binary").join(used, "v").dropDuplicates(["v"])), "v")


def by_fingerprint(texts: DataFrame) -> DataFrame:
    """Pairs (a, b), a < b, that the Gray-order index over SimHash fingerprints proposes: a spanning forest of its
    classes, in which the texts of one fingerprint hang on the least of them."""
    rows = written(fingerprints(texts, "v", "text", WIDTH).distinct())
    fps = written(rows.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("n")))
    total = rows.count()
    same = join_groups(rows, fps, "fp", "n", total).where("id != least").select(F.col("least").alias("a"), F.col("id").alias("b"))
    least = lambda of: fps.select(F.col("fp").alias(of), F.col("least").alias(f"least_{of}"))
    near = near_edges(fps.select("fp"), total, BITS).withColumnsRenamed({"a": "fp_a", "b": "fp_b"}).join(least("fp_a"), "fp_a").join(least("fp_b"), "fp_b")
    near = near.select(F.least("least_fp_a", "least_fp_b").alias("a"), F.greatest("least_fp_a", "least_fp_b").alias("b"))
    return same.unionByName(near).distinct()


def passing(texts: DataFrame, pairs: DataFrame, exact: bool) -> DataFrame:
    """Pairs that pass by_sketch or by_set. Only what is compared is shuffled, and only of texts in pairs."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = [shingles(t.as_py()) for t in b.column(1)]
            yield batch(v=b.column(0), size=pa.array([len(x) for x in sets], pa.int64()), own=pa.array([(x if exact else sketch(x)).tobytes() for x in sets], pa.binary()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test, kind = (by_set, U) if exact else (by_sketch, np.uint8)
        for b in batches:
            keep = [test(np.frombuffer(x.as_buffer(), kind), np.frombuffer(y.as_buffer(), kind), m) for x, y, m in zip(b.column(2), b.column(3), b.column(4).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    used = written(pairs.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count("*").alias("n")))
    own = written(map_batches(among(texts, used), made, "v long, size long, own binary").join(used, "v").dropDuplicates(["v"]))
    total = pairs.count()
    side = lambda v: own.select(F.col("v").alias(v), "n", F.col("own").alias(f"own_{v}"), F.col("size").alias(f"size_{v}"))
    left = join_groups(pairs, side("a"), "a", "n", total).drop("n")
    both = join_groups(left, side("b"), "b", "n", total)
    return written(map_batches(both.select("a", "b", "own_a", "own_b", F.expr("size_a + size_b")), run, "a long, b long"))


def verified(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs whose whole sets agree by four fifths; sketches, which miss none, spare most of the sets' traffic."""
    return passing(texts, passing(texts, pairs, False), True)


def near_copies(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", rounds: int = 3) -> DataFrame:
    """(id, component_id) of the rows of every class of two texts or more, component_id the smallest id of the class."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    texts = df.select(F.xxhash64(text).alias("v"), text.alias("text"))
    tried = written(by_fingerprint(texts))
    roots = components(verified(texts, tried))
    hits = written(shared_only(prefixes(texts, frequent(texts))))
    for k in range(rounds):
        driver_gives_back(df.sparkSession)
        whole = k == rounds - 1
        rows = hits.join(roots, "v", "left").select("tok", "v", "size", "pos", "fp", F.coalesce("root", "v").alias("root"))
        if whole:
            rows = with_parities(texts, written(undecided(rows))).select(*rows.columns, "wide")
        pairs = written(candidates(rows, k, whole).join(tried, ["a", "b"], "left_anti"))
        tried = tried.unionByName(pairs)
        if not pairs.isEmpty() and not (new := verified(texts, pairs)).isEmpty():
            roots = components(new.unionByName(roots.select(F.col("v").alias("a"), F.col("root").alias("b"))))
    driver_gives_back(df.sparkSession)
    ids = df.select(F.xxhash64(text).alias("v"), F.col(id_col).alias("id")).join(roots.select("v", "root").unionByName(roots.select(F.col("root").alias("v"), "root").distinct()), "v")
    ids = written(ids)
    least = written(ids.groupBy("root").agg(F.min("id").alias("component_id"), F.count("*").alias("n")))
    return join_groups(ids, least, "root", "n", ids.count()).select(F.col("id").alias(id_col), "component_id")
