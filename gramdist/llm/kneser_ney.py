"""Interpolated modified Kneser-Ney language model, counted in Spark, kept as sorted hash arrays, mapped by workers.

Tokens: words split at ASCII white space, A-Z lower-cased, then one end token a text. A first pass counts them by their
64-bit hashes, in ranges, and numbers them: about in order of frequency, since a range's most frequent words get the
smallest numbers. An n-gram and a context are 64-bit hashes of their tokens' numbers.

Counting: tasks fold the n-grams of some TOKENS_AT_ONCE tokens into sorted distinct ones and send each range of contexts
one packed block (columns of numbers, small ones being frequent, compressed). A range is merged in one piece and written as two files of sorted hashes (n-grams with counts; contexts with their total and how many words
follow once, twice, more). Distinct n-grams of one order send the next lower order its continuation counts.

A hash table is a file of buckets by leading bits, in each the next 32 bits in order, and a byte for each that numbers
its values in a list of those that occur, most frequent first; rarer values are listed by place. Counts are of any
size.

Hot contexts: n-grams of a context whose tokens are all hot are dealt by n-gram instead, so that no range holds more
than its share; the totals of such contexts are summed by a second shuffle. A token is hot from RANGE_TOKENS / 4
occurrences on, or from 1 in MOST_HOT of the text if that is more, so MOST_HOT bounds what is sent to all tasks; any
other context has fewer occurrences than its rarest token.

Scoring maps the files and looks up the distinct n-grams of large batches; the files lie in the shared folder (copied
once a worker where that folder is no file system). What is gathered grows with the text: all n-grams of all training
texts.

Nulls and ties: a null or empty text is its end token alone; repeated rows count each time; a null id trains. An
empty table gives no rows; with no training text every token has the chance that unseen words have. Other columns
are not read. Texts are read whole, a long one over several batches.
"""

from __future__ import annotations

import itertools
import json
import os
import tempfile
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, crc, map_batches, on_workers, scratch_dir, table

ORDER = 3
U = np.uint64
BEGIN, END = (xxhash.xxh64_intdigest(x, 1) for x in (b"\n<", b"\n>"))  # no word holds a line break
NEW = -1  # the number of words that training texts don't have; 0 is what comes before a text
TOKENS_AT_ONCE = 1_000_000  # that a task folds or scores at a time
RANGE_TOKENS = 2_000_000
MOST_HOT = 4_000_000  # 32 MB
WORDS_AT_ONCE = 400_000  # distinct words that a task counts at a time
MAPS = 8_000  # files that a worker holds mapped; systems allow some 65,000
BLOCK = "kind string, part int, data binary"


def mix(a: np.ndarray, b) -> np.ndarray:
    with np.errstate(over="ignore"):
        z = a * U(0x9E3779B97F4A7C15) + b
        z = (z ^ (z >> U(31))) * U(0xBF58476D1CE4E5B9)
    return z ^ (z >> U(29))


def narrow(x: np.ndarray) -> np.ndarray:
    """The same whole numbers in the fewest bytes that hold the largest."""
    return x.astype(np.min_scalar_type(int(x.max())) if len(x) else np.uint8)


class Words(defaultdict):
    """Word -> number in order of first use: 0 begins a text, 1 ends it; next come tokens of which only hashes are known."""

    def __init__(self, known: list[int] | tuple = ()):
        super().__init__(itertools.count(2 + len(known)).__next__)
        self.known = [BEGIN, END, *known]

    def hashes(self) -> np.ndarray:
        return np.array([*self.known, *map(xxhash.xxh64_intdigest, self)], U)


def batches_of(texts, order: int, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, list[int]]]:
    """(n-grams of every token as numbers, hashes of the numbers, tokens of each text here) of some `most` tokens at a
    time. A text that begins in one batch and goes on in the next has a count in both. Column 0 is the word, column k
    the k-th token before it."""
    pad = order - 1
    words, flat, sizes, held = Words(), [np.zeros(pad, np.uint32)], [], 0

    def made() -> tuple[np.ndarray, np.ndarray, list[int]]:
        all_ = np.concatenate(flat)
        at = np.concatenate([np.arange(n) + s for n, s in zip(sizes, np.cumsum([pad, *[n + pad for n in sizes]]))]) if sizes else np.zeros(0, np.int64)
        return np.stack([all_[at - k] for k in range(order)], 1), words.hashes(), sizes

    for t in texts:
        own = (t.as_py() or "").encode().lower().split()
        before = np.zeros(pad, np.uint32)
        for s in range(0, len(own) + 1, most):
            some = own[s : s + most]
            ids = np.empty(len(some) + (s + most > len(own)), np.uint32)
            ids[: len(some)] = np.fromiter(map(words.__getitem__, some), np.uint32, len(some))
            if s + most > len(own):
                ids[-1] = 1
            if sizes:
                flat.append(before)
            else:
                flat = [before]
            flat.append(ids)
            sizes.append(len(ids))
            held += len(ids)
            if held >= most:
                done = made()
                yield done
                on = s + most <= len(own)  # the text goes on: its last tokens begin the next batch
                last = done[1][np.concatenate([before, ids])[len(ids) :]].tolist() if on else []
                words, flat, sizes, held = Words(last), [np.zeros(pad, np.uint32)], [], 0
                if on:
                    before = np.arange(2, 2 + pad, dtype=np.uint32)
            elif pad:
                before = np.concatenate([before, ids])[-pad:]
    if sizes:
        yield made()


def distinct(grams: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct rows, contexts together, and in order where numbers are small; number of each row's) of n-grams of
    numbers below size."""
    bits, order = max(1, (size - 1).bit_length()), grams.shape[1]
    if bits * order > 64:
        key, ctx = keys_of(grams)
        at = np.lexsort((key, ctx)) if ctx is not None else np.argsort(key)
        new = np.r_[True, np.diff(key[at].view(np.int64)) != 0] if len(at) else np.zeros(0, bool)
        back = np.empty(len(at), np.int64)
        back[at] = np.cumsum(new) - 1
        return grams[at[new]], back
    code = np.zeros(len(grams), U)
    for k in (*range(1, order), 0):
        code = code << U(bits) | grams[:, k].astype(U)
    code, back = np.unique(code, return_inverse=True)
    out = np.empty((len(code), order), np.int64)
    for k in (0, *range(order - 1, 0, -1)):
        out[:, k] = code & U((1 << bits) - 1)
        code = code >> U(bits)
    return out, back


def keys_of(grams: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
    """(hash of each n-gram of token numbers, hash of its context)."""
    g = grams.astype(np.int64).view(U)
    if g.shape[1] == 1:
        return mix(g[:, 0], U(5)), None
    ctx = mix(g[:, 1], U(3))
    for k in range(2, g.shape[1]):
        ctx = mix(ctx, g[:, k])
    return mix(ctx, g[:, 0]), ctx


def part_of(key: np.ndarray, parts: int) -> np.ndarray:
    return ((mix(key, U(7)) >> U(20)) % U(parts)).astype(np.uint16 if parts <= 1 << 16 else np.int64)


def all_hot(grams: np.ndarray, hot: np.ndarray) -> np.ndarray:
    """Is every token of the context hot? 0 always is."""
    return np.isin(grams[:, 1:], hot).all(axis=1) if grams.shape[1] > 1 else np.zeros(len(grams), bool)


def parts_of(grams: np.ndarray, hot: np.ndarray, key: np.ndarray, ctx: np.ndarray | None, parts: int) -> np.ndarray:
    """Range of each n-gram: by its context, or by itself where that is hot."""
    return part_of(key if ctx is None else np.where(all_hot(grams, hot), key, ctx), parts)


def slices(part: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(part, places) for every part that occurs."""
    order = np.argsort(part, kind="stable")
    if len(order):
        cut = np.flatnonzero(np.r_[True, np.diff(part[order]) != 0])
        for s, e in zip(cut, [*cut[1:], len(order)]):
            yield int(part[order[s]]), order[s:e]


def planes(x: np.ndarray, width: int) -> bytes:
    """The lowest `width` bytes of every number, all first bytes first: alike ones lie together."""
    return np.ascontiguousarray(np.ascontiguousarray(x.astype("<u8")).view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def from_planes(raw: bytes, n: int, width: int) -> np.ndarray:
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(width, n).T
    return out.view("<u8").reshape(-1)


def blocks(grams: np.ndarray, n: np.ndarray, parts: int, hot: np.ndarray) -> Iterator[tuple]:
    """Packed rows of distinct n-grams in order, one for each range: the steps of the nearest token, the other columns."""
    key, ctx = keys_of(grams)
    squeeze = zstandard.ZstdCompressor(level=3)
    for part, at in slices(parts_of(grams, hot, key, ctx, parts)):
        cols = [*grams[at].T, n[at]]
        if len(cols) > 2:
            cols[1] = np.diff(cols[1], prepend=0)
        yield "block", part, squeeze.compress(packed(cols))


def packed(cols: list[np.ndarray]) -> bytes:
    widths = [max(1, (int(c.max()).bit_length() + 7) // 8) for c in cols]
    return b"".join([np.array([len(cols[0]), *widths], "<i8").tobytes(), *(planes(c, w) for c, w in zip(cols, widths))])


def unpack(rows: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """(n-grams, counts) of blocks."""
    grams, count = [np.zeros((0, order), np.int64)], [np.zeros(0, np.int64)]
    for data in rows:
        raw = zstandard.ZstdDecompressor().decompress(data)
        n, *widths = np.frombuffer(raw, "<i8", order + 2).tolist()
        at, cols = 8 * (order + 2), []
        for w in widths:
            cols.append(from_planes(raw[at : at + n * w], n, w).astype(np.int64))
            at += n * w
        if order > 1:
            cols[1] = np.cumsum(cols[1])
        grams.append(np.stack(cols[:-1], 1))
        count.append(cols[-1])
    return np.concatenate(grams), np.concatenate(count)


def store(uri: str) -> tuple[pafs.FileSystem, str]:
    if uri.startswith("file:"):
        uri = "/" + uri.removeprefix("file:").lstrip("/")
    return (pafs.LocalFileSystem(), uri) if uri.startswith("/") else pafs.FileSystem.from_uri(uri)


def coded(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of each row, different rows), most frequent rows first. Single small numbers need no sorting."""
    if values.shape[1] == 1 and len(values) and 0 <= values.min() and values.max() < 1 << 16:
        every = np.bincount(values[:, 0])
        own = np.flatnonzero(every)
        back, times, kinds = None, every[own], own[:, None]
    else:
        mark = values[:, 0].astype(U)
        for k in range(1, values.shape[1]):
            mark = mix(mark, values[:, k].astype(U))
        _, first, back, times = np.unique(mark, return_index=True, return_inverse=True, return_counts=True)
        kinds = values[first]
    by_use = np.argsort(-times, kind="stable")
    rank = np.empty(len(by_use), np.int64)
    rank[by_use] = np.arange(len(by_use))
    if back is None:
        place = np.zeros(len(every), np.int64)
        place[own] = rank
        return place[values[:, 0]], kinds[by_use]
    return rank[back], kinds[by_use]


def save(uri: str, name: str, key: np.ndarray, values: np.ndarray, number: np.ndarray | None = None) -> None:
    """A hash table of distinct keys with a row of whole numbers each, and one number of its own if given. Written under another name and then moved, so a
    task that is run twice leaves one whole file."""
    order = np.argsort(key)
    key, values = key[order], values[order]
    bits = max(0, (len(key) // 8).bit_length())
    bucket = (key >> U(64 - bits)).astype(np.int64) if bits else np.zeros(len(key), np.int64)
    start = np.r_[0, np.cumsum(np.bincount(bucket, minlength=1 << bits))]
    code, kinds = coded(values)
    rare = np.flatnonzero(code >= 255)
    arrays = [start.astype("<u4"), (key >> U(32 - bits)).astype("<u4"), np.minimum(code, 255).astype(np.uint8), rare.astype("<u4"), code[rare].astype("<u4"), kinds.astype("<i8")]
    if number is not None:
        arrays.append(number[order].astype("<i8"))
    head = np.array([len(key), bits, int(np.diff(start).max(initial=0)), len(rare), len(kinds), values.shape[1]], "<i8")
    raw = b"".join(x.tobytes() + bytes(-x.nbytes % 8) for x in [head, *arrays])
    fs, at = store(uri)
    fs.create_dir(at)
    tmp = f"{at}/.{name}-{os.getpid()}-{os.urandom(4).hex()}"
    with fs.open_output_stream(tmp) as f:
        f.write(raw)
    fs.move(tmp, f"{at}/{name}.hashes")


class Table:
    """A file of save(), mapped."""

    def __init__(self, path: str):
        raw = np.asarray(np.memmap(path, np.uint8, "r"))
        n, self.bits, self.most, rare, kinds, width = np.frombuffer(raw[:48], "<i8").tolist()
        at = 48

        def take(kind: str, count: int) -> np.ndarray:
            nonlocal at
            size = np.dtype(kind).itemsize * count
            out = raw[at : at + size].view(kind)
            at += size + -size % 8
            return out

        self.start, self.low, self.code = take("<u4", (1 << self.bits) + 1), take("<u4", n), take("u1", n)
        self.rare, self.rare_code, self.values = take("<u4", rare), take("<u4", rare), take("<i8", kinds * width).reshape(kinds, width)
        self.number = take("<i8", n) if at + 8 * n <= len(raw) else None

    def find(self, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(which keys are here, their places)."""
        if not len(self.low):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        bucket = (key >> U(64 - self.bits)).astype(np.int64) if self.bits else np.zeros(len(key), np.int64)
        low = (key >> U(32 - self.bits)).astype(np.uint32)
        lo, end = self.start[bucket].astype(np.int64), self.start[bucket + 1].astype(np.int64)
        for k in reversed(range(self.most.bit_length())):
            last = lo + ((1 << k) - 1)  # of the next 2**k, all of which are passed if it is less
            less = self.low.take(last, mode="clip") < low
            less &= last < end
            np.add(lo, 1 << k, out=lo, where=less)
        hit = np.flatnonzero((lo < end) & (self.low.take(lo, mode="clip") == low))
        return hit, lo[hit]

    def get(self, key: np.ndarray, numbers: bool = False) -> np.ndarray:
        """A row of values for every key, 0 where it is absent; with numbers its own number too, NEW where absent."""
        out = np.zeros((len(key), self.values.shape[1] + numbers))
        if numbers:
            out[:, -1] = NEW
        hit, at = self.find(key)
        code = self.code[at].astype(np.int64)
        if len(often := np.flatnonzero(code == 255)):
            code[often] = self.rare_code[np.searchsorted(self.rare, at[often])]
        out[hit, : self.values.shape[1]] = self.values[code]
        if numbers:
            out[hit, -1] = self.number[at]
        return out


@lru_cache(maxsize=MAPS)
def mapped(uri: str, name: str) -> Table | None:
    fs, at = store(uri)
    path = f"{at}/{name}.hashes"
    if not isinstance(fs, pafs.LocalFileSystem):
        local = os.path.join(_copies(uri), f"{name}.hashes")
        if fs.get_file_info(path).type != pafs.FileType.File:
            return None
        if not os.path.exists(local):
            pafs.copy_files(path, local, source_filesystem=fs, destination_filesystem=pafs.LocalFileSystem())
        path = local
    return Table(path) if os.path.exists(path) else None


def drop(uri: str) -> None:
    fs, at = store(uri)
    fs.delete_dir(at)


@lru_cache(maxsize=4)
def _copies(uri: str) -> str:
    import atexit
    import shutil

    path = tempfile.mkdtemp()
    atexit.register(shutil.rmtree, path, True)
    return path


def look_up(uri: str, prefix: str, key: np.ndarray, part: np.ndarray, width: int = 1) -> np.ndarray:
    """Values of keys in the tables of their ranges, 0 where absent."""
    out = np.zeros((len(key), width))
    for r, at in slices(part):
        t = mapped(uri, f"{prefix}-{r}")
        if t is not None:
            out[at] = t.get(key[at])
    return out


def numbered(uri: str, hashes: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """(counts, numbers) of tokens by their hashes."""
    out = np.zeros((len(hashes), 2))
    out[:, 1] = NEW
    key = mix(hashes, U(5))
    for r, at in slices(part_of(key, parts)):
        t = mapped(uri, f"raw-{r}")
        if t is not None:
            out[at] = t.get(key[at], True)
    return out[:, 0], np.where(hashes == U(BEGIN), 0, out[:, 1].astype(np.int64))


def counted(docs: DataFrame, order: int, parts: int, hot: np.ndarray, uri: str, word_parts: int) -> DataFrame:
    """Blocks of the n-grams of the texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for grams, hashes, _ in batches_of((t for b in batches for t in b.column(0)), order, TOKENS_AT_ONCE):
            own = numbered(uri, hashes, word_parts)[1]
            at = np.argsort(own, kind="stable")
            turn = np.empty(len(at), np.uint32)
            turn[at] = np.arange(len(at), dtype=np.uint32)
            grams, back = distinct(turn[grams], len(at))
            yield rows_batch(list(blocks(own[at][grams], np.bincount(back, minlength=len(grams)), parts, hot)))

    return map_batches(docs.select("text"), run, BLOCK)


def words_counted(docs: DataFrame, parts: int) -> DataFrame:
    """Hashes and counts of the tokens of the texts, packed for each range."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, ends = Counter(), 0

        def flush() -> pa.RecordBatch:
            hashes = np.array([END, *map(xxhash.xxh64_intdigest, seen)], U)
            n, out = np.array([ends, *seen.values()], np.int64), []
            for r, at in slices(part_of(mix(hashes, U(5)), parts)):
                out.append(("block", r, zstandard.compress(hashes[at].tobytes() + planes(n[at], 5), 1)))
            return rows_batch(out)

        for b in batches:
            for t in b.column(0):
                seen.update((t.as_py() or "").encode().lower().split())
                ends += 1
                if len(seen) >= WORDS_AT_ONCE:
                    yield flush()
                    seen, ends = Counter(), 0
        yield flush()

    return map_batches(docs.select("text"), run, BLOCK)


def words_merged(rows: DataFrame, uri: str, parts: int, least_hot: int) -> DataFrame:
    """Sum the counts of every range's tokens, number them and write its table; gives statistics and which are hot."""
    on_workers(rows.sparkSession)

    def run(t: pa.Table) -> pa.Table:
        part = t.column("part")[0].as_py()
        raw = [zstandard.decompress(d) for d in t.column("data").to_pylist()]
        hashes = np.concatenate([np.frombuffer(d, U, len(d) // 13) for d in raw])
        n = np.concatenate([from_planes(d[8 * (len(d) // 13) :], len(d) // 13, 5) for d in raw]).astype(np.int64)
        hashes, back = np.unique(hashes, return_inverse=True)
        sums = np.zeros(len(hashes), np.int64)
        np.add.at(sums, back, n)
        hashes, sums = hashes[sums > 0], sums[sums > 0]
        number = np.empty(len(hashes), np.int64)
        number[np.argsort(-sums, kind="stable")] = 1 + part + parts * np.arange(len(hashes))
        save(uri, f"raw-{part}", mix(hashes, U(5)), sums[:, None], number)
        stat = {"of": [0] * 4, "sum": int(sums.sum()), "types": len(sums), "hot": number[sums >= least_hot].tolist()}
        return pa.Table.from_batches([rows_batch([("stat", part, json.dumps(stat).encode())])])

    return rows.groupBy("part").applyInArrow(run, BLOCK)


def rows_batch(rows: list[tuple]) -> pa.RecordBatch:
    kind, part, data = zip(*rows) if rows else [()] * 3
    return batch(kind=pa.array(kind, pa.string()), part=pa.array(part, pa.int32()), data=pa.array(data, pa.binary()))


def follows(key: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(contexts, (total, words that follow once, twice, more)) of n-grams' contexts and counts."""
    at = np.argsort(key)
    key, n = key[at], n[at]
    cut = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)
    cols = [np.add.reduceat(x.astype(np.int64), cut) if len(cut) else np.zeros(0, np.int64) for x in (n, n == 1, n == 2, n > 2)]
    return key[cut], np.stack(cols, 1)


def merged(rows: DataFrame, order: int, uri: str, name: str, parts: int, hot: np.ndarray) -> DataFrame:
    """Merge the blocks of every range, write its tables, and give statistics, the totals of hot contexts and the lower
    order's blocks."""
    on_workers(rows.sparkSession)

    def run(t: pa.Table) -> pa.Table:
        part = t.column("part")[0].as_py()
        grams, n = unpack(t.column("data").to_pylist(), order)
        size = int(grams.max()) + 1
        grams, back = distinct(grams, size)
        sums = np.zeros(len(grams), np.int64)
        np.add.at(sums, back, n)
        n = sums
        key, ctx = keys_of(grams)
        save(uri, f"{name}-{part}", key, n[:, None])
        stat = {"of": [int((n == k).sum()) for k in (1, 2, 3, 4)], "sum": int(n.sum()), "types": len(n)}
        out = [("stat", part, json.dumps(stat).encode())]
        if ctx is not None:
            shared = all_hot(grams, hot)
            save(uri, f"{name}c-{part}", *follows(ctx[~shared], n[~shared]))
            c, sums = follows(ctx[shared], n[shared])
            for r, at in slices(part_of(c, parts)):
                out.append(("hot", r, zstandard.compress(np.column_stack([c[at], sums[at].astype(U)]).astype("<u8").tobytes())))
            lower, back = distinct(grams[:, :-1], size)
            out += blocks(lower, np.bincount(back, minlength=len(lower)), parts, hot)
        return pa.Table.from_batches([rows_batch(out)])

    return rows.groupBy("part").applyInArrow(run, BLOCK)


def hot_totals(rows: DataFrame, uri: str, name: str) -> None:
    """Sum what ranges have of hot contexts and write the tables."""

    def run(t: pa.Table) -> pa.Table:
        x = np.concatenate([np.frombuffer(zstandard.decompress(d), "<u8").reshape(-1, 5) for d in t.column("data").to_pylist()])
        c, back = np.unique(x[:, 0], return_inverse=True)
        sums = np.zeros((len(c), 4), np.int64)
        np.add.at(sums, back, x[:, 1:].astype(np.int64))
        save(uri, f"{name}-{t.column('part')[0].as_py()}", c, sums)
        return pa.Table.from_batches([rows_batch([])])

    rows.where("kind = 'hot'").groupBy("part").applyInArrow(run, BLOCK).count()


def total(rows: DataFrame) -> dict:
    """Sum of the ranges' statistics; one small row a range comes to the driver."""
    out = {"of": [0] * 4, "sum": 0, "types": 0, "hot": []}
    for r in rows.where("kind = 'stat'").select("data").toLocalIterator():
        s = json.loads(bytes(r[0]))
        out["of"] = [a + b for a, b in zip(out["of"], s["of"])]
        out["sum"] += s["sum"]
        out["types"] += s["types"]
        out["hot"] += s.get("hot", [])
    return out


def discounts(of: list[int]) -> list[float]:
    """What is taken off counts 0, 1, 2 and more, from how many n-grams have counts 1 to 4."""
    n1, n2, n3, n4 = of
    y = n1 / (n1 + 2 * n2) if n1 else 0.5
    raw = [k - (k + 1) * y * b / a if a else 0.5 * k for k, a, b in ((1, n1, n2), (2, n2, n3), (3, n3, n4))]
    return [0.0, *[min(max(d, 0.05), k - 0.05) for k, d in zip((1, 2, 3), raw)]]


def tidied(rows: DataFrame, path: str) -> None:
    """Write a table; the files that its shuffle leaves are removed at once, not when the driver next collects garbage."""
    conf, name = rows.sparkSession.conf, "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = conf.get(name, None)
    conf.set(name, "true")
    try:
        rows.write.parquet(path)
    finally:
        conf.unset(name) if before is None else conf.set(name, before)


def train(docs: DataFrame, order: int = ORDER, least_hot: int = RANGE_TOKENS // 4) -> dict:
    """Count the texts (column text) and write the model; returns its small description."""
    if order < 2:
        raise ValueError("order must be 2 or more")
    spark = docs.sparkSession
    uri = scratch_dir(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # every token is a byte and a blank at least, so no more tokens than this: the bound that few tokens are hot needs
    letters = docs.agg(F.coalesce(F.sum(F.length("text") + 2), F.lit(0))).first()[0]
    least_hot = max(least_hot, letters // (2 * MOST_HOT))
    model = {"uri": uri, "order": order, "word_parts": max(parts, letters // (1000 * RANGE_TOKENS))}

    def stage(rows: DataFrame, name: str) -> DataFrame:
        path = f"{uri}/rows-{name}"
        tidied(rows, path)
        return spark.read.schema(BLOCK).parquet(path)

    words = model["word_parts"]
    raw = total(stage(words_merged(words_counted(docs, words), uri, words, least_hot), "raw"))
    model |= {"tokens": raw["sum"], "types": raw["types"]}
    parts = model["parts"] = max(parts, raw["sum"] // RANGE_TOKENS)
    hot = model["hot"] = np.array([0, *sorted(raw["hot"])])
    rows = counted(docs, order, parts, hot, uri, words)
    for k in range(order, 0, -1):
        rows = stage(merged(rows, k, uri, f"o{k}", parts, hot), f"o{k}")
        stat = total(rows)
        model[f"d{k}"], model[f"sum{k}"] = discounts(stat["of"]), stat["sum"]
        model[f"of{k}"] = stat["of"] + [stat["types"]]
        if k > 1:
            hot_totals(rows, uri, f"o{k}h")
        if k < order:
            drop(f"{uri}/rows-o{k + 1}")  # its blocks are in this order's tables now
        rows = rows.where("kind = 'block'")
    drop(f"{uri}/rows-o1")
    drop(f"{uri}/rows-raw")
    return model


def chances_of(model: dict, grams: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(raw count of each hash, probability of each n-gram's word after its context) of distinct n-grams, contexts
    together; n-grams hold places in hashes."""
    uri, parts, hot = model["uri"], model["parts"], model["hot"]
    raw, number = numbered(uri, hashes, model["word_parts"])
    word, _ = keys_of(number[:, None])
    cont = look_up(uri, "o1", word, part_of(word, parts))[:, 0] * (number != NEW)
    d, whole, of = model["d1"], model["sum1"], model["of1"]
    uniform = 1 / (model["types"] + 1)
    if whole:
        kept = sum(d[k] * c for k, c in ((1, of[0]), (2, of[1]), (3, of[4] - of[0] - of[1])))
        p = (cont - np.take(d, np.minimum(cont, 3).astype(int))) / whole + kept / whole * uniform
    else:
        p = np.full(len(hashes), uniform)
    # the n-grams of every order among these, each with the place of its lower one
    levels, lower = [(grams, None)], grams
    while lower.shape[1] > 2:
        lower, back = distinct(lower[:, :-1], len(hashes))
        levels[-1] = (levels[-1][0], back)
        levels.append((lower, None))
    for own, back in reversed(levels):
        k = own.shape[1]
        tokens = number[own]
        key, ctx = keys_of(tokens)
        shared = all_hot(tokens, hot)
        n = look_up(uri, f"o{k}", key, part_of(np.where(shared, key, ctx), parts))[:, 0]
        # n-grams lie together by their contexts; those of several new words may look alike, and have nothing
        cut = np.flatnonzero(np.r_[True, ctx[1:] != ctx[:-1]]) if len(ctx) else np.zeros(0, np.int64)
        c, split = ctx[cut], shared[cut]
        stats = np.zeros((len(c), 4))
        for name, at in ((f"o{k}c", np.flatnonzero(~split)), (f"o{k}h", np.flatnonzero(split))):
            stats[at] = look_up(uri, name, c[at], part_of(c[at], parts), 4)
        stats = np.repeat(stats, np.diff(np.r_[cut, len(ctx)]), axis=0)
        d, whole = model[f"d{k}"], stats[:, 0]
        kept = d[1] * stats[:, 1] + d[2] * stats[:, 2] + d[3] * stats[:, 3]
        some = np.maximum(whole, 1)
        low = p[own[:, 0]] if k == 2 else p[back]
        p = np.where(whole > 0, (n - np.take(d, np.minimum(n, 3).astype(int))) / some + kept / some * low, low)
    return raw, p


def chances(model: dict, tokens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(raw count of the word, probability of the word after its context) of rows of token hashes: the word, the token
    before it, the one before that."""
    hashes, ranks = np.unique(tokens, return_inverse=True)
    ranks = ranks.reshape(tokens.shape).astype(np.uint32)
    grams, back = distinct(ranks, len(hashes))
    raw, p = chances_of(model, grams, hashes)
    return raw[ranks[:, 0]], p[back]


def scored(batches: Iterator[pa.RecordBatch], model: dict) -> Iterator[pa.RecordBatch]:
    """score of batches (id, held_out, text). N-grams are looked up once for TOKENS_AT_ONCE tokens, however small the
    batches are; a text's figures leave when its last token is scored."""
    n, v, waiting, i = model["tokens"], model["types"], [], pa.int64()

    def texts() -> Iterator[pa.Scalar]:
        for b in batches:
            if not b.num_rows:
                continue
            every = pa.array(np.arange(b.num_rows))
            waiting.append([b.column(k).take(every) for k in (0, 1)])  # copies, or the texts would stay with them
            yield from b.column(2)

    def taken(rows: int) -> list[pa.Array]:
        out = []
        while rows:
            some = waiting[0]
            out.append([c[:rows] for c in some])
            if len(some[0]) > rows:
                waiting[0] = [c[rows:] for c in some]
            else:
                del waiting[0]
            rows -= len(out[-1][0])
        return [pa.concat_arrays(c) for c in zip(*out)]

    part = np.zeros(4)  # of a text that goes on
    for grams, hashes, sizes in batches_of(texts(), model["order"], TOKENS_AT_ONCE):
        rows, back = distinct(grams, len(hashes))
        raw, p = chances_of(model, rows, hashes)
        word = grams[:, 0]
        cut = np.cumsum([0, *sizes])[:-1]
        cols = np.ones(len(word)), raw[word] > 0, np.log10((raw + 1) / (n + v + 1))[word], np.log10(p)[back]
        sums = np.stack([np.add.reduceat(x.astype(float), cut) for x in cols], axis=1)
        sums[0] += part
        part = np.zeros(4)
        if word[-1] != 1:  # the last text goes on
            sums, part = sums[:-1], sums[-1]
        if len(sums):
            ids, held = taken(len(sums))
            yield batch(id=ids, held_out=held, n_tokens=pa.array(sums[:, 0].astype(np.int64), i), n_known=pa.array(sums[:, 1].astype(np.int64), i), train_tokens=pa.array(np.full(len(sums), n), i), base_score=pa.array(sums[:, 2]), score=pa.array(sums[:, 3]))


def score(docs: DataFrame, model: dict) -> DataFrame:
    """docs (id, held_out, text) -> counts, the base and the model's log10 probability of every text."""
    kind = docs.schema["id"].dataType.simpleString()
    return map_batches(docs.select("id", "held_out", "text"), lambda batches: scored(batches, model), f"id {kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def perplexity(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", folds: int = 7, held: int = 2, order: int = ORDER, least_hot: int = RANGE_TOKENS // 4) -> DataFrame:
    """Train on the rows whose id's CRC-32 mod folds is not held; score all rows. Adds the perplexity per token."""
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(crc(id_col) % folds == held, F.lit(False)).alias("held_out"), F.col(text_col).alias("text"))
    model = train(rows.where("NOT held_out").select("text"), order, least_hot)
    out = score(rows, model).withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")))
    return out.withColumnRenamed("id", id_col)


def op2_kneser_ney(spark, sf_dir: str) -> DataFrame:
    return perplexity(table(spark, sf_dir, "documents"))
