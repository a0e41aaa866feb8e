"""Every operator against a brute-force version, and on odd and empty tables."""

from __future__ import annotations

import hashlib
import json
import math
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pyarrow.fs as pafs
import pytest
import xxhash
import zstandard
from pyspark.sql import functions as F

from gramdist.llm import bloom_dedup, chat, compression_rules, kneser_ney, lang_fusion, mil_toxicity, mixing, packing, pu_quality, simhash

SPLIT = re.compile(r"[^\x20\x09-\x0D]+")


def texts(df):
    return [(r.doc_id, r.text or "") for r in df.select("doc_id", "text").collect()]


# --- exact dedup ---------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("words", [bloom_dedup.MAX_WORDS, 1])  # 1: a filter that is full, as far beyond its size
def test_exact_dedup(odd, none, words):
    out = bloom_dedup.exact_dedup(odd, max_words=words).collect()
    assert len(out) == 12
    groups = defaultdict(list)
    for r in out:
        groups[r.text or ""].append(r)
    for text, g in groups.items():
        top = max((r.doc_id for r in g if r.doc_id is not None), default=None)
        assert {r.keep_id for r in g} == {top} and {r.group_size for r in g} == {len(g)}
        kept = [r for r in g if r.kept]
        assert len(kept) == 1 and kept[0].doc_id == top
        assert g[0].text_sha256 == hashlib.sha256(text.encode()).hexdigest()
    assert bloom_dedup.exact_dedup(none, max_words=words).count() == 0


@pytest.mark.parametrize("rows", [100, 5000, 10**9])
def test_bloom_flags_all_repeats_and_few_others(spark, rows):
    """Cells of any width hit twice; the filter holds all of them and lets most of the others pass."""
    df = spark.range(5000).select(F.xxhash64(F.concat(F.lit("t"), F.col("id") % 4000)).alias("h"))
    own = df.select("h", bloom_dedup.cell(rows, F.col("h")).alias("c"))
    again = own.groupBy("c").count().where("count >= 2").select(F.xxhash64("c").alias("_h"))
    bloom = bloom_dedup.filter_of(again)
    got = bloom_dedup.flagged(own.select("h", F.xxhash64("c").alias("_h")), bloom).groupBy("h").agg(F.count("*").alias("n"), F.max("_maybe").alias("m")).collect()
    assert all(r.m for r in got if r.n > 1)
    if rows >= 5000:
        assert sum(r.m for r in got if r.n == 1) < 0.1 * len(got)


def test_without_ids(odd, none):
    gone = odd.where("doc_id IN (2, 7)").select("doc_id").distinct()
    for words in (bloom_dedup.MAX_WORDS, 1):
        got = bloom_dedup.without_ids(odd, gone, max_words=words)
        assert got.columns == odd.columns
        assert Counter(r.doc_id for r in got.collect()) == Counter(r.doc_id for r in odd.collect() if r.doc_id not in (2, 7))
    assert bloom_dedup.without_ids(none, gone).count() == 0 and bloom_dedup.without_ids(odd, gone.limit(0)).count() == 12


# --- simhash -------------------------------------------------------------------------------------------------------


def slow_fingerprint(text: str) -> int:
    words = SPLIT.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text))
    if not words:
        return 0
    shingles = [" ".join(words[k : k + 3]) for k in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def slow_classes(rows, most=2):
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (rows[i][1] ^ rows[j][1]).bit_count() <= most:
                parent[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(least.get(find(i), d), d)
    return [least.get(find(i)) for i in range(len(rows))]


def check_classes(df, **options):
    out = simhash.near_duplicates(df, **options).collect()
    rows = [(d, slow_fingerprint(t)) for d, t in texts(df)]
    want = Counter((d, f"{f:016x}", c) for (d, f), c in zip(rows, slow_classes(rows)))
    assert Counter((r.doc_id, r.fingerprint, r.component_id) for r in out) == want


def test_simhash(odd, none, documents):
    check_classes(odd)
    check_classes(documents)
    assert simhash.near_duplicates(none).count() == 0


@pytest.mark.parametrize("hot_rows", [100_000, 3])
def test_gray_index_finds_all_links(spark, hot_rows):
    r = np.random.default_rng(1)
    base = r.integers(0, 2**63, 12, dtype=np.uint64)
    fps = [int(b) ^ (1 << int(r.integers(64))) ^ (1 << int(r.integers(64))) ^ (1 << int(r.integers(64))) for b in base for _ in range(30)]
    fps = sorted({int(np.uint64(x).astype(np.int64)) for x in fps})
    df = spark.createDataFrame([(x,) for x in fps], "fp long")
    roots = {x.v: x.root for x in simhash.components(simhash.near_edges(df, len(fps), 2, hot_rows)).collect()}
    got = [roots.get(x, x) for x in fps]
    want = slow_classes([(k, x & (2**64 - 1)) for k, x in enumerate(fps)])
    assert len(set(zip(got, want))) == len(set(got)) == len(set(want))
    own = np.array(fps).view(np.uint64)
    own = own[np.argsort(simhash.gray_rank(own))]
    label = simhash.GrayIndex(own).links(2)
    assert len(set(label)) == len(set(want))


def test_small_batches_are_looked_up_together(monkeypatch):
    import pyarrow as pa

    calls = []

    def chances(model, grams, hashes):
        calls.append(len(grams))
        return np.arange(len(hashes)).astype(float), 1 / (1 + hashes[grams[:, 0]].astype(float))

    monkeypatch.setattr(kneser_ney, "chances_of", chances)
    model = {"tokens": 10, "types": 4, "order": 3}
    texts = ["a b c", "", None, "a b", "b b b b b b b b b", "c"] * 4
    one = lambda k: pa.RecordBatch.from_pydict({"id": [k], "held_out": [k % 2 == 0], "text": pa.array([texts[k]], pa.string())})
    got = pa.Table.from_batches(list(kneser_ney.scored(map(one, range(len(texts))), model)))
    assert len(calls) == 1 and got["id"].to_pylist() == list(range(len(texts)))
    assert got["n_tokens"].to_pylist() == [len((t or "").split()) + 1 for t in texts]
    monkeypatch.setattr(kneser_ney, "TOKENS_AT_ONCE", 4)  # texts go on from batch to batch
    again = pa.Table.from_batches(list(kneser_ney.scored(map(one, range(len(texts))), model)))
    assert len(calls) > 10 and again["id"].to_pylist() == got["id"].to_pylist() and again["n_tokens"] == got["n_tokens"]
    assert np.allclose(again["score"].to_numpy(), got["score"].to_numpy())


@pytest.mark.parametrize("n", [0, 60, 400])
def test_classes_of_few_edges_take_one_task(spark, n):
    r = np.random.default_rng(n)
    ids = r.integers(-(2**62), 2**62, 300)
    edges = [(int(ids[a]), int(ids[b])) for a, b in r.integers(0, 300, (n, 2))]
    df = spark.createDataFrame(edges, "a long, b long")
    sc = spark.sparkContext
    sc.setJobGroup(f"few-edges-{n}", "")
    got = simhash.components(df)
    jobs = len(sc.statusTracker().getJobIdsForGroup(f"few-edges-{n}"))
    sc.setLocalProperty("spark.jobGroup.id", None)
    assert jobs <= 8 and sorted(got.collect()) == sorted(simhash.components(df, 0).collect())
    least = {x: x for e in edges for x in e}
    for _ in least:
        for a, b in edges:
            least[a] = least[b] = min(least[a], least[b])
    assert dict(got.collect()) == {v: m for v, m in least.items() if v != m}


def test_gray_rank():
    codes = np.array([k ^ k >> 1 for k in range(200)], np.uint64)
    assert simhash.gray_rank(codes).tolist() == list(range(200))


# --- language model --------------------------------------------------------------------------------------------------


def slow_model(docs, order):
    tok = lambda t: [x.lower() for x in t.encode().split()] + [b"\n"]
    train = [tok(t) for i, t in docs if i is None or zlib.crc32(str(i).encode()) % 7 != 2]
    raw = Counter(x for d in train for x in d)
    total, types = sum(raw.values()), len(raw)
    counts = Counter()
    for d in train:
        d = [b""] * (order - 1) + d
        counts.update(tuple(d[k - order + 1 : k + 1]) for k in range(order - 1, len(d)))
    by = {order: counts}
    for k in range(order - 1, 0, -1):
        by[k] = Counter(g[1:] for g in by[k + 1])
    off, sums, kinds = {}, {}, {}
    for k, t in by.items():
        off[k] = kneser_ney.discounts([sum(v == n for v in t.values()) for n in (1, 2, 3, 4)])
        sums[k], kinds[k] = Counter(), defaultdict(Counter)
        for g, v in t.items():
            sums[k][g[:-1]] += v
            kinds[k][g[:-1]][min(v, 3)] += 1

    def p(k, ctx, w):
        if k == 0:
            return 1 / (types + 1)
        c = ctx[len(ctx) - k + 1 :] if k > 1 else ()
        low = p(k - 1, ctx, w)
        if not sums[k][c]:
            return low
        n = by[k].get((*c, w), 0)
        return (n - off[k][min(n, 3)]) / sums[k][c] + sum(off[k][m] * kinds[k][c][m] for m in (1, 2, 3)) / sums[k][c] * low

    out = []
    for i, t in docs:
        d = tok(t)
        e = [b""] * (order - 1) + d
        own = sum(math.log10(p(order, tuple(e[k : k + order - 1]), e[k + order - 1])) for k in range(len(d)))
        out.append((i, len(d), sum(raw[x] > 0 for x in d), total, sum(math.log10((raw[x] + 1) / (total + types + 1)) for x in d), own))
    return out


@pytest.mark.parametrize("order, least_hot", [(2, 10**6), (3, 10**6), (3, 3), (4, 40)])  # few, many and some hot contexts
def test_language_model(documents, odd, order, least_hot):
    for df in (documents, odd):
        want = Counter((a, b, c, d, round(e, 4), round(f, 4)) for a, b, c, d, e, f in slow_model(texts(df), order))
        got = kneser_ney.perplexity(df, order=order, least_hot=least_hot).collect()
        assert Counter((r.doc_id, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4), round(r.score, 4)) for r in got) == want


def test_language_model_beats_base(documents, none):
    held = kneser_ney.perplexity(documents).where("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert held[0] > held[1]
    assert kneser_ney.perplexity(none).count() == 0


def test_production_order_scores_better_and_leaves_no_blocks(documents):
    score = lambda order: kneser_ney.perplexity(documents, **order).where("held_out").agg(F.sum("score")).first()[0]
    assert kneser_ney.ORDER >= 3 and score({}) > score({"order": 2})
    model = kneser_ney.train(documents.select("text"))
    fs, at = kneser_ney.store(model["uri"])
    assert not [f.path for f in fs.get_file_info(pafs.FileSelector(at)) if "/rows-" in f.path]


def test_model_sums_to_one(spark, documents):
    model = kneser_ney.train(documents.where("doc_id < 20").select("text"))
    words = sorted({w for _, t in texts(documents.where("doc_id < 20")) for w in t.encode().lower().split()})
    h = np.array([*(xxhash.xxh64_intdigest(w, 0) for w in words), kneser_ney.END, 12345], np.uint64)
    of = lambda w: xxhash.xxh64_intdigest(w, 0)
    first = next(t.encode().lower().split() for _, t in texts(documents.where("doc_id < 20")) if len(t.split()) > 3)
    for one, two in ((words[0], words[5]), (first[1], first[0]), (first[2], first[1]), (words[5], b"never seen"), (b"never seen", b"nor this")):
        rows = np.stack([h, np.full(len(h), of(one), np.uint64), np.full(len(h), of(two), np.uint64)], 1)
        assert kneser_ney.chances(model, rows)[1].sum() == pytest.approx(1, abs=1e-6)


def test_texts_of_any_length_are_read_over_batches(spark):
    import pyarrow as pa

    r = np.random.default_rng(3)
    docs = [" ".join(f"w{k}" for k in r.integers(0, 9, n)) for n in (0, 1, 7, 40, 3, 8, 16, 0, 25)]

    def read(most):
        out, sizes = [], 0
        for grams, hashes, own in kneser_ney.batches_of(pa.array(docs), 3, most):
            out += [tuple(hashes[k].tolist()) for k in grams]
            sizes += sum(own)
            assert sum(own) == len(grams)
        assert sizes == len(out)
        return out

    assert all(read(most) == read(10**6) for most in (1, 2, 5, 8, 16, 30))


def test_hash_tables(tmp_path):
    r = np.random.default_rng(4)
    for n in (0, 1, 7, 5000):
        key = np.unique(r.integers(0, 2**64, n, dtype=np.uint64))
        values = r.zipf(1.3, (len(key), 4)).clip(0, 2**40)
        kneser_ney.save(str(tmp_path), f"t{n}", key, values)
        t = kneser_ney.mapped(str(tmp_path), f"t{n}")
        assert (t.get(key) == values).all() and not t.get(r.integers(0, 2**64, 1000, dtype=np.uint64)).any()


# --- packing -----------------------------------------------------------------------------------------------------------


def test_packing(odd, none, documents):
    from tokenizers import Tokenizer

    path = packing.default_tokenizer()
    slow = Tokenizer.from_file(path)
    for df in (odd, documents):
        out = packing.pack(df, path, with_ids=True).collect()
        assert len({r.sequence_id for r in out}) == len(out)
        got = Counter()
        by = defaultdict(list)
        for r in out:
            assert r.length & (r.length - 1) == 0 and r.length <= 2048 and r.offset == 0 and r.bucket == r.length
            assert zlib.crc32(np.array(r.ids, "<u4").tobytes()) == r.ids_crc32
            by[r.doc_id, r.doc_tokens].append(r)
        whole = Counter()
        for d, t in texts(df):
            ids = [*slow.encode(t, add_special_tokens=False).ids, 1]
            whole[d, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
        for (d, n), pieces in by.items():
            for same in zip(*[[p for p in pieces if p.start == s] for s in sorted({p.start for p in pieces})]):
                ids = [i for p in same for i in p.ids]
                got[d, n, zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
        assert got == whole
    assert packing.pack(none, path).count() == 0


def test_cut_is_binary():
    for n in (1, 2, 2047, 2048, 2049, 5000):
        parts = packing.cut(n, 2048)
        assert sum(parts) == n and all(p & (p - 1) == 0 for p in parts) and max(Counter(p for p in parts if p < 2048).values(), default=1) == 1


@pytest.mark.parametrize("text", ["<|endoftext|> in a text<|endoftext|>", "a" * 3000, "   x\r\n\r\n  y", "’s I'LL we'll 12345"])
def test_fast_encoder_is_the_tokenizer(text):
    from tokenizers import Tokenizer

    path = packing.default_tokenizer()
    assert list(packing.encoder(path)(text)) == Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids


def test_other_tokenizers_run_as_they_are():
    import public_tokenizers

    assert packing.encoder(str(public_tokenizers.path("word_bpe_49k.json")))("Hello world")


# --- rules -------------------------------------------------------------------------------------------------------------


def test_rules(odd, none, documents):
    squeeze = zstandard.ZstdCompressor(level=compression_rules.LEVEL)
    for df in (odd, documents):
        want = Counter()
        for d, t in texts(df):
            words = SPLIT.findall(t)
            windows = Counter(tuple(words[k : k + 5]) for k in range(len(words) - 4))
            again = {k + j for k in range(len(words) - 4) if windows[tuple(words[k : k + 5])] > 1 for j in range(5)}
            lines, seen, dups = t.split("\n"), set(), 0
            for x in lines:
                if SPLIT.search(x):
                    dups += x in seen
                    seen.add(x)
            failed = len(words) < 10 or 100 * len(again) > 20 * len(words)
            raw = t.encode()
            ratio = len(squeeze.compress(raw)) / len(raw) if raw else None
            want[d, len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), dups, len(again), failed, ratio] += 1
        got = compression_rules.judge(df).collect()
        assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed, r.ratio) for r in got) == want
        assert not any(r.kept and r.base_failed for r in got)
    assert compression_rules.judge(none).count() == 0


def test_bands_keep_good_and_drop_bad(spark, sf):
    rng = np.random.default_rng(3)
    noise = "".join(chr(33 + int(k)) for k in rng.integers(0, 90, 6000))
    df = spark.createDataFrame([(1, " ".join(noise[k : k + 40] for k in range(0, 6000, 40))), (2, " ".join("ab"[k % 2] * (1 + k % 7) for k in range(900)))], "doc_id long, text string")
    assert {r.doc_id: r.kept for r in compression_rules.judge(df).collect()} == {1: False, 2: False}
    got = compression_rules.judge(spark.read.parquet(f"{sf}/documents.parquet")).join(spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1"), "doc_id").where("NOT base_failed")
    assert got.where("kept").count() >= 0.99 * got.count()


def test_bands_drop_random_letters(spark, sf):
    """Random letters at every size where texts and noise differ, and a text with noise in its second half or tail."""
    rng = np.random.default_rng(4)
    kinds = {128: "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", 1024: "abcdefghijklmnopqrstuvwxyz", 2048: "0123456789abcdef"}

    def noise(letters, n):
        s = "".join(letters[k] for k in rng.integers(0, len(letters), n))
        return " ".join(s[k : k + 8] for k in range(0, n, 8))[:n]

    rows = [noise(x, n) for least, x in kinds.items() for n in (200, 600, 1000, 3000, 12_000, 40_000) if n >= least]
    long = max((r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect() if r.text), key=len)
    assert len(long) > 5000
    rows += [long[: len(long) // 2] + " " + noise(kinds[128], len(long) // 2), long[:4096] + " " + noise(kinds[128], 3000)]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    assert [r.doc_id for r in compression_rules.judge(df).where("kept").collect()] == []


# --- classifiers ---------------------------------------------------------------------------------------------------------


def test_toxicity(spark):
    sf = "/root/testdata/sf0.01"
    out = mil_toxicity.op5_mil_toxicity(spark, sf)
    l = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "toxic")
    a = out.join(l, "doc_id").where("held_out").select((F.col("toxic") == F.col("predicted")).cast("int").alias("ok")).agg(F.avg("ok")).first()[0]
    assert a > 0.93 and out.count() == 1000


def test_toxicity_spans_and_edges(spark, odd, none):
    good = [(k, f"fine words number {k} here. all is well today"[: 30 + k % 9], 0) for k in range(60)]
    bad = [(100 + k, f"fine words number {k} here. you are such a zorkish person. all is well", 1) for k in range(60)]
    docs = spark.createDataFrame([(a, b) for a, b, _ in good + bad], "doc_id long, text string")
    labels = spark.createDataFrame([(a, c) for a, _, c in good + bad] + [(None, 1), (5, None)], "doc_id long, toxic int")
    model = mil_toxicity.train(docs, labels)
    rows = mil_toxicity.annotate(docs, model).collect()
    for r, (_, text, y) in zip(sorted(rows, key=lambda r: r.doc_id), good + bad):
        assert r.predicted == y
        if y:
            assert len(r.offending) == 1 and "zorkish" in text[r.offending[0].start : r.offending[0].end]
    assert mil_toxicity.annotate(odd, model).count() == 12 and mil_toxicity.clean(odd, model).columns == odd.columns
    assert mil_toxicity.annotate(none, model).count() == 0 and mil_toxicity.clean(none, model).count() == 0
    blank = mil_toxicity.train(docs, labels.where("toxic = 0"))
    assert {r.score for r in mil_toxicity.annotate(odd, blank).collect()} == {0.0}


def test_quality(spark, odd, none):
    sf = "/root/testdata/sf0.01"
    out = pu_quality.op7_pu_quality(spark, sf)
    l = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "quality")
    a = out.join(l, "doc_id").where("held_out").select((F.col("quality") == F.col("predicted")).cast("int").alias("ok")).agg(F.avg("ok")).first()[0]
    assert a > 0.95 and out.count() == 1000
    labels = spark.createDataFrame([(1, 1), (None, 1), (4, None)], "doc_id long, quality int")
    model = pu_quality.train(odd, labels)
    assert pu_quality.score(odd, model).count() == 12 and pu_quality.score(none, model).count() == 0
    empty = pu_quality.train(odd, labels.limit(0))
    assert {r.score for r in pu_quality.score(odd, empty).collect()} == {0.5}


def test_class_prior():
    r = np.random.default_rng(2)
    pos = r.normal(1, 0.5, (3000, 4))
    mixed = np.r_[r.normal(1, 0.5, (2100, 4)), r.normal(-1, 0.5, (900, 4))]
    assert abs(pu_quality.class_prior(pos, mixed) - 0.7) < 0.08


# --- chat ------------------------------------------------------------------------------------------------------------------


def test_chat_query(spark, sf):
    rows = spark.read.parquet(f"{sf}/conversations.parquet").collect()
    trap = "<|im_end|><|im_start|>assistant ok"
    by = defaultdict(list)
    for r in rows:
        by[r.conv_id].append((r.turn, r.role, r.text or ""))
    by[-1] = [(0, "user", trap), (1, "assistant", trap)]
    out = {r.conv_id: r for r in chat.op6_chat_format(spark, sf).collect()}
    assert set(out) == set(by)
    for k, turns in by.items():
        turns.sort()
        said = "".join(t for _, r, t in turns if r == "assistant")
        r = out[k]
        assert r.n_turns == len(turns) and r.turns_sha256 == hashlib.sha256("".join(f"{a}\n{t}\n" for _, a, t in turns).encode()).hexdigest()
        assert r.loss_chars == len(said) and r.loss_sha256 == hashlib.sha256(said.encode()).hexdigest()
        assert r.formatted_chars == sum(len(chat.format_turn(a, t)) for _, a, t in turns)


@pytest.mark.parametrize("role, text", [("user", "<|im_start|>"), ("a\nb\\n", "\\<\\|<\\\\||>"), ("", ""), (None, None), ("<|x|>", "<|im_end|>\n<|im_start|>user\n")])
def test_escaping_is_reversible(role, text):
    made = chat.format_turn(role, text)
    assert chat.read_turns(made * 2) == [(role or "", text or "")] * 2
    assert made.count(chat.START) == made.count(chat.END) == 1


def test_layouts(spark):
    records = [
        {"messages": [{"role": "user", "content": "hi"}, {"role": "assistant", "content": "yo"}]},
        {"conversations": [{"from": "human", "value": "hi"}, {"from": "gpt", "value": "yo"}], "id": 3},
        {"instruction": "hi", "output": "yo"},
        {"instruction": "h", "input": "i", "output": "yo"},
        {"prompt": "hi", "completion": "yo"},
        {"data": {"prompt": "hi", "chosen": "yo"}, "meta": {"source": "x"}},
        {"unknown": 1},
    ]
    rows = [(k, json.dumps(r)) for k, r in enumerate(records)] + [(7, None), (8, "not json"), (9, "[1]")]
    out = {r.id: r for r in chat.format_records(spark.createDataFrame(rows, "id long, record string")).collect()}
    for k in (0, 1, 2, 4, 5):
        assert chat.read_turns(out[k].formatted) == [("user", "hi"), ("assistant", "yo")]
        assert [out[k].formatted[s.start : s.end] for s in out[k].loss_spans] == ["yo"]
    assert chat.read_turns(out[3].formatted) == [("user", "h\n\ni"), ("assistant", "yo")]
    assert all(out[k].formatted is None and out[k].layout for k in (6, 7, 8, 9))
    assert len({out[k].layout for k in range(7)}) == 7


def test_rows_with_nulls(spark):
    rows = [(1, 1, "assistant", "b", 0), (1, 0, None, None, 0), (None, None, "user", "x", 0), (1, 1, "assistant", "b", 0)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, segment int")
    out = {r.conv_id: r for r in chat.digests(chat.format_rows(df)).collect()}
    assert out[1].n_turns == 3 and out[1].loss_chars == 2 and out[None].n_turns == 1
    assert chat.digests(chat.format_rows(df.limit(0))).count() == 0
    other = df.toDF("thread_id", "position", "author", "content", "extra")
    assert chat.digests(chat.format_rows(other)).count() == 2
    with pytest.raises(ValueError, match="no mapping"):
        chat.format_rows(df.drop("role"))


# --- mixing ----------------------------------------------------------------------------------------------------------------


def test_mix_is_the_sql(spark, sf):
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    cols = ("doc_id", "size", "source_size", "target", "taken", "copies")
    want = {r[0]: (*r[1:3], round(r[3], 6), *r[4:]) for r in c.sql(f"SELECT {', '.join(cols)} FROM ({mixing.ORACLE})").fetchall()}
    got = {r.doc_id: (r.size, r.source_size, round(r.target, 6), r.taken, r.copies) for r in mixing.op8_mix_sources(spark, sf).collect()}
    assert got == want


def slow_targets(sizes):
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    left, total, out, open_ = dict.fromkeys(order), sum(sizes.values()), {}, set(order)
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    while True:
        level = (total - sum(out.values())) / sum(weight[s] for s in open_)
        over = {s for s in open_ if level * weight[s] > 3 * sizes[s]}
        if not over:
            return out | {s: level * weight[s] for s in open_}, left
        out |= {s: 3 * sizes[s] for s in over}
        open_ -= over


def test_mix_targets_and_edges(odd, none, documents):
    for df in (odd, documents):
        rows = mixing.mix(df).collect()
        sizes = Counter()
        for r in rows:
            assert r.size == len(SPLIT.findall(r.text or "")) and r.taken == r.copies * r.size <= 3 * r.size
            sizes[r.source] += r.size
        want, _ = slow_targets(dict(sizes))
        taken, largest = Counter(), Counter()
        for r in rows:
            assert r.target == pytest.approx(want[r.source]) and r.source_size == sizes[r.source]
            taken[r.source] += r.taken
            largest[r.source] = max(largest[r.source], r.size)
        for s, t in want.items():
            assert t - largest[s] <= taken[s] <= t + 1e-6
    assert mixing.mix(none).count() == 0 and mixing.mix_rows(none).count() == 0


def test_mix_rows_deal_exact_quotas(documents):
    plan = {r.doc_id: r.copies for r in mixing.mix(documents).collect()}
    rows = mixing.mix_rows(documents, depth=2, words_per_block=256).collect()
    assert Counter(r.doc_id for r in rows) == Counter({k: v for k, v in plan.items() if v})
    assert {r.shard for r in rows} <= set(range(4)) and len({r.shard for r in rows}) == 4
    small = mixing.mix(documents, words_per_block=1)  # blocks of a word: the edge is searched over several levels
    assert {r.doc_id: r.copies for r in small.collect()} == plan
    drawn = mixing.mixed(documents, depth=2, words_per_block=256)
    order = [r.doc_id for part in drawn.rdd.glom().collect() for r in part]
    assert drawn.columns == documents.columns and Counter(order) == Counter(r.doc_id for r in rows)
    by_shard = {}
    for r in sorted(rows, key=lambda r: (r.shard, r.place)):
        by_shard.setdefault(r.shard, []).append(r.doc_id)
    text = ",".join(map(str, order))
    assert all(",".join(map(str, ids)) in text for ids in by_shard.values())
    again = mixing.mix_rows(documents.repartition(5), depth=2, words_per_block=256).collect()
    assert Counter((r.doc_id, r.shard, r.place) for r in rows) == Counter((r.doc_id, r.shard, r.place) for r in again)


def test_splitting_tree_halves_every_node(spark):
    slots = spark.range(1000).select(F.concat(F.lit("s"), (F.col("id") % 3).cast("string")).alias("source"), F.lit(0).cast("long").alias("epoch"), F.col("id").alias("block"))
    out = mixing.splitting_tree(slots, 3, 17)
    assert {r["count"] for r in out.groupBy("shard").count().collect()} == {125}
    by = {(r.shard, r.source): r["count"] for r in out.groupBy("shard", "source").count().collect()}
    assert all(20 <= n <= 65 for n in by.values())


# --- languages ---------------------------------------------------------------------------------------------------------------


def test_languages(spark, sf):
    every = lang_fusion.op10_lang_fusion(spark, sf).collect()
    rows = {r.page_id: r for r in every if r.page_id is not None}
    docs = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert np.mean([docs[r.doc_id] == r.lang for r in every if r.doc_id is not None]) > 0.97 and len(every) == len(rows) + len(docs)
    pages = {r.page_id: r.url for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    assert set(rows) == set(pages)
    assert np.mean([f"/{rows[p].lang}/" in u for p, u in pages.items()]) > 0.95
    assert all(0 < r.probability <= 1 for r in rows.values())


def test_language_edges(spark, odd):
    model = lang_fusion.train(odd.where("lang IN ('en', 'de')"))
    pages = spark.createDataFrame([(1, None, None), (2, "http://a.example.de/x", ""), (2, "http://a.example.de/x", ""), (None, "not an address", "<html lang=de>" + "straße ünï " * 9), (3, "HTTPS://user@B.example.DE:80/y", "<html lang='EN-us'><script>x</script>the quick brown fox")], "page_id long, url string, html string")
    out = lang_fusion.fused(pages, model).collect()
    assert len(out) == 5 and {r.lang for r in out} <= {"en", "de"} and sum(r.host == "b.example.de" for r in out) == 1
    assert {r.page_id: r.declared for r in out}[3] == "en"
    assert lang_fusion.fused(pages.limit(0), model).count() == 0
    assert lang_fusion.fused_texts(odd, model).count() == 12
    nothing = lang_fusion.fused(pages, lang_fusion.train(odd.limit(0))).collect()
    assert len(nothing) == 5 and {r.lang for r in nothing} == {None}


# --- very long and hostile texts -----------------------------------------------------------------------------------------


@pytest.mark.parametrize("piece", [" ", "\n", "a", "<!--", "<script ", "<style>", "<html ", "<", "&#99999999999", "lang = ", "word "])
def test_two_million_letters_of_one_kind(piece):
    """Every kernel ends in seconds, whatever a text repeats."""
    import time

    text = piece * (2_000_000 // len(piece))
    squeeze = zstandard.ZstdCompressor(level=1)
    start = time.time()
    ids = packing.encoder(packing.default_tokenizer())(text)
    assert len(ids) > 1000
    lang_fusion.page_text(text), lang_fusion.declared_lang(text)
    simhash.fingerprint(text)
    compression_rules.base_measures(text)
    pu_quality.statistics(text, squeeze)
    mil_toxicity.sentence_scores({"bias": -5.0, "weights": {"word": 1.0}}, text, {})
    assert time.time() - start < 90


def test_pages_are_read_as_by_plain_patterns():
    hidden, tag = re.compile(r"<!--.*?-->|<(script|style|nav)\b.*?</\1\s*>", re.S | re.I), re.compile(r"<[^>]*>")
    declared = re.compile(r"<html\b[^>]*?\blang\s*=\s*[\"']?([A-Za-z]+)", re.I)
    r = np.random.default_rng(2)
    marks = ["<!--", "-->", "<script>", "</script >", "<style", "</style>", "<nav ", "</NAV>", ">", "<", "a b", "<html ", "lang=", "'de'", " lang = en", "&amp;", "x", "\n"]
    import html

    for _ in range(3000):
        page = "".join(r.choice(marks, r.integers(0, 14)))
        assert lang_fusion.page_text(page) == html.unescape(tag.sub(" ", hidden.sub(" ", page)))
        said = declared.search(page)
        assert lang_fusion.declared_lang(page) == (said[1].lower() if said else "")


def test_long_texts_as_short_ones():
    r = np.random.default_rng(6)
    for n in (3, 4, 5, 6, 50, 400):
        words = [b"w%d" % k for k in r.integers(0, 4, n)]
        assert compression_rules.repeated_words(words, long=0) == compression_rules.repeated_words(words)
    text, at_once = " ".join(f"w{k}" for k in r.integers(0, 50, 1000)), simhash.AT_ONCE
    want = simhash.fingerprint(text)
    try:
        for simhash.AT_ONCE in (1, 7, 996, 997, 998, 999):
            assert simhash.fingerprint(text) == want
    finally:
        simhash.AT_ONCE = at_once


def test_words_are_numbered_without_a_call_each():
    words = kneser_ney.Words([7, 9])
    assert "__missing__" not in vars(kneser_ney.Words)
    assert [words[w] for w in (b"b", b"a", b"b", b"c")] == [4, 5, 4, 6]
    h = [xxhash.xxh64_intdigest(w, 0) for w in (b"b", b"a", b"c")]
    assert words.hashes().tolist() == [kneser_ney.BEGIN, kneser_ney.END, 7, 9, *h]


def test_values_of_a_table_are_coded_most_frequent_first():
    for values in ([[3], [1], [3], [70_000]], [[3], [1], [3], [0]], [[5, 1], [5, 2], [5, 1]], np.zeros((0, 1), int)):
        values = np.array(values, np.int64)
        code, kinds = kneser_ney.coded(values)
        assert (kinds[code] == values).all() and (np.diff(np.bincount(code, minlength=1)) <= 0).all()
        assert len(kinds) == len({tuple(v) for v in values.tolist()})
