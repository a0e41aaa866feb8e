"""The pipeline's stages against what they say they do."""

from __future__ import annotations

import random
from collections import Counter

import corpus_pipeline as P
from gramdist.llm import mil_toxicity, packing, shingle_join


def test_stages(spark, documents, sf):
    docs, seen = documents, {}
    for name, stage in P.STAGES:
        before = docs
        docs = stage(spark, docs, sf)
        docs.write.mode("overwrite").parquet(path := f"/tmp/gramdist-test-{name}")
        docs = spark.read.parquet(path)
        seen[name] = (before, docs)
        if name != P.STAGES[-1][0]:
            assert docs.columns == documents.columns
    ids = lambda df: Counter(r.doc_id for r in df.select("doc_id").collect())
    model = mil_toxicity.train(documents, spark.read.parquet(f"{sf}/labels.parquet"))
    assert ids(seen["toxicity"][1]) == ids(mil_toxicity.annotate(documents, model).where("predicted = 0"))
    a, b = seen["exact_dedup"]
    best = {}
    for r in a.collect():
        best[r.text] = max(best.get(r.text, -1), r.doc_id)
    assert ids(b) == Counter(best.values())
    a, b = seen["near_dedup"]
    assert set(ids(b)) <= set(ids(a))
    a, b = seen["mix_sources"]
    assert set(ids(b)) <= set(ids(a)) and max(ids(b).values()) <= 3
    a, b = seen["pack_binary"]
    assert set(ids(b)) == set(ids(a))
    assert sorted(P.run(spark, sf).columns) == sorted(b.columns)


def test_odd_and_empty_tables(spark, odd, none, sf):
    for table, n in ((odd, 12), (none, 0)):
        for name, stage in P.STAGES:
            out = stage(spark, table, sf)
            if name != "pack_binary":
                assert out.columns == table.columns
            rows = out.count()
            assert rows == 0 if not n else rows > 0
    assert packing.pack(odd, packing.default_tokenizer()).count() >= 12


def shingle_words(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)}


def test_near_dedup_is_brute_force(spark, sf):
    """Every pair with five-word Jaccard >= 0.8 is linked, whatever its fingerprints' distance, and no other pair."""
    r = random.Random(5)
    rows = [(x.doc_id, x.text) for x in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").dropDuplicates(["text"]).orderBy("doc_id").limit(250).collect()]
    for k in range(120):  # copies with edits from the first word on, and one family of chained copies
        w = rows[k if k < 80 else 3][1].split()
        for _ in range(1 + k % 6):
            w[r.randrange(len(w))] = f"edit{k}"
        rows.append((10_000 + k, " ".join(w)))
    rows += [(20_000, "a b c"), (20_001, "A  b c"), (20_002, ""), (20_003, " ")]
    sets = [shingle_words(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            shared = len(sets[i] & sets[j])
            if 5 * shared >= 4 * (len(sets[i]) + len(sets[j]) - shared):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    least = {}
    for k, (d, _) in enumerate(rows):
        least[find(k)] = min(d, least.get(find(k), d))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert len(least) < len(rows) - 60
    assert Counter(x.doc_id for x in P.near_dedup(spark, docs, sf).collect()) == Counter(least.values())


def test_near_dedup_asks_the_gray_order_index_first(spark, monkeypatch):
    """Near copies within the index's bits are proposed by it, and the exact search has no pair left to verify."""
    r = random.Random(8)
    words = [f"w{r.randrange(900)}" for _ in range(1500)]
    rows = [(k, " ".join([*words[: 10 * k], f"edit{k}", *words[10 * k + 1 :]])) for k in range(1, 13)]
    asked, seen = [], []
    near_edges, verified = shingle_join.near_edges, shingle_join.verified
    monkeypatch.setattr(shingle_join, "near_edges", lambda *x: asked.append(x[2]) or near_edges(*x))
    monkeypatch.setattr(shingle_join, "verified", lambda t, p: seen.append(p.count()) or verified(t, p))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert [x.doc_id for x in P.near_dedup(spark, docs, "").collect()] == [1]
    assert asked == [shingle_join.BITS] and seen[0] >= 8


def test_group_below_the_limit_makes_few_candidates(spark, monkeypatch):
    """400 texts that share most shingles, but less than four fifths: pairs to verify don't grow with their square."""
    r = random.Random(9)
    base, rows = [f"w{k}" for k in range(160)], []
    for k in range(400):
        w = list(base)
        for at in r.sample(range(160), 5):
            w[at] = f"edit{k}x{at}"
        rows.append((k, " ".join(w)))
    seen = []
    verified = shingle_join.verified
    monkeypatch.setattr(shingle_join, "verified", lambda t, p: seen.append(p.count()) or verified(t, p))
    sets = [shingle_words(t) for _, t in rows]
    linked = {i for i in range(400) for j in range(400) if i != j and 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j]))}
    got = {x.doc_id for x in shingle_join.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == linked
    assert sum(seen) < 8_000
