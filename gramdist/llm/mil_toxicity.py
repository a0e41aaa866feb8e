"""Toxicity by multiple-instance learning: a document is a bag of sentences, only bags are labelled.

A sentence scores sigmoid(bias + sum of the weights of its distinct words and word beginnings); a document's score
is the noisy-or of its sentences, 1 - prod(1 - p). Weights are fitted to document labels by maximising the bags' likelihood, and
the same weights then say which sentences are to blame. Words are letter runs in lower case, so markup and
punctuation are no input; label, language, source and id are none either.

Fit: at most SAMPLE documents of each label (those with the smallest hash of their id), reweighted to the labels'
true shares; features of fewer than LEAST_DOCS sampled documents are left out. Everything else covers all rows.

Nulls and ties: a null or empty text has no sentence and scores the model's background (near 0); a null label is
no label; an id labelled twice counts once, toxic if any row says so; rows repeat as they are; without both
labels to learn from, every score is 0. An empty table gives no rows. Extra columns are carried by annotate only.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, crc, map_batches, table, written

SAMPLE = 2000
LEAST_DOCS = 4
BEGINNINGS = (4, 5, 6, 7)
WORDS = re.compile(r"[^\W\d_]+")
SENTENCE = re.compile(r"[^.!?\n]+")


def features(word: str) -> list[str]:
    """A word and its beginnings, so that inflected and derived forms share evidence."""
    return [word, *[f"{word[:k]}-" for k in BEGINNINGS if k <= len(word)]]


def sentences(text: str) -> list[tuple[int, int]]:
    """Spans between full stops, exclamation and question marks and line ends."""
    return [m.span() for m in SENTENCE.finditer(text) if not m.group().isspace()]


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, usable, per_class: int) -> tuple[DataFrame, dict]:
    """(id, text, y) of at most per_class documents of each label, and how many documents each label has."""
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).where(usable).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    known = known.where("y IN (0, 1)")
    sizes = {r["y"]: r["count"] for r in known.groupBy("y").count().collect()}
    picked = [known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for y in (0, 1)]
    chosen = picked[0].unionByName(picked[1])  # at most 2 * per_class rows
    return docs.select(F.col("doc_id").alias("id"), "text").join(F.broadcast(chosen.withColumnRenamed("doc_id", "id")), "id"), sizes


def vocabulary_of(sample: DataFrame) -> dict[str, int]:
    """Features of at least LEAST_DOCS sampled documents, numbered in order; counted in tasks, then summed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, int] = {}
        for b in batches:
            for t in b.column(0):
                for f in {f for w in set(WORDS.findall((t.as_py() or "").lower())) for f in features(w)}:
                    seen[f] = seen.get(f, 0) + 1
        yield batch(feature=pa.array(list(seen), pa.string()), n=pa.array(list(seen.values()), pa.int64()))

    counts = map_batches(sample.select("text"), run, "feature string, n long").groupBy("feature").agg(F.sum("n").alias("n"))
    return {f: k for k, f in enumerate(sorted(r.feature for r in counts.where(F.col("n") >= LEAST_DOCS).toLocalIterator()))}


def bags(sample: DataFrame, vocabulary: dict[str, int]) -> DataFrame:
    """Each document as the numbers of its sentences' distinct features, and how many each sentence has, packed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            feats, sizes = [], []
            for t in b.column(0):
                text, own, n = (t.as_py() or "").lower(), [], []
                for s, e in sentences(text):
                    found = sorted({vocabulary[f] for w in set(WORDS.findall(text, s, e)) for f in features(w) if f in vocabulary})
                    own += found
                    n.append(len(found))
                feats.append(np.array(own, "<i4").tobytes())
                sizes.append(np.array(n, "<i4").tobytes())
            yield batch(feats=pa.array(feats, pa.binary()), sizes=pa.array(sizes, pa.binary()), y=b.column(1))

    return map_batches(sample.select("text", "y"), run, "feats binary, sizes binary, y int")


def fit(bag_rows: list[tuple[bytes, bytes, int]], names: list[str], sizes: dict[int, int], rounds: int = 200, rate: float = 0.15, shrink: float = 2e-4) -> dict:
    """Feature weights and bias by full-batch Adam on the weighted likelihood of the noisy-or."""
    bag_rows = sorted(bag_rows)
    y = np.array([r[2] for r in bag_rows], float)
    if not 0 < y.sum() < len(y):
        return {"bias": -math.inf, "weights": {}}
    tok = np.concatenate([np.frombuffer(r[0], "<i4") for r in bag_rows])
    lines = [np.frombuffer(r[1], "<i4") for r in bag_rows]
    doc = np.repeat(np.arange(len(lines), dtype=np.int32), [len(x) for x in lines])
    sent = np.repeat(np.arange(len(doc), dtype=np.int32), np.concatenate(lines))
    share = sum(sizes.values())
    weight = np.where(y > 0, sizes.get(1, 0) / share / y.mean(), sizes.get(0, 0) / share / (1 - y.mean())) / len(y)
    w, b, m, v = np.zeros(len(names)), -5.0, np.zeros(len(names) + 1), np.zeros(len(names) + 1)
    for k in range(1, rounds + 1):
        s = b + np.bincount(sent, w[tok], len(doc))
        p = 1 / (1 + np.exp(-s))
        clean = -np.bincount(doc, np.logaddexp(0, s), len(y))  # log of the chance that no sentence is toxic
        clean = np.minimum(clean, -1e-9)
        # d loss / d clean is 1 / (exp(-clean) - 1) for toxic documents and -1 for others
        slope = np.where(y > 0, 1 / np.expm1(np.minimum(-clean, 50)), -1.0) * weight
        g_s = slope[doc] * -p
        g = np.r_[np.bincount(tok, g_s[sent], len(w)) + shrink * np.sign(w) * (w != 0), g_s.sum()]
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        step = rate * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    return {"bias": float(b), "weights": {names[k]: float(w[k]) for k in np.flatnonzero(np.abs(w) > 0.2)}}


def sentence_scores(model: dict, text: str, known: dict) -> list[tuple[int, int, float]]:
    weights, bias = model["weights"], model["bias"]
    low = text.lower()
    same = len(low) == len(text)
    out = []
    for s, e in sentences(text if same else low):
        found = {f for w in set(WORDS.findall(low, s, e)) for f in hits(w, weights, known)}
        out.append((s, e, bias + sum(weights[f] for f in sorted(found))))
    return out


def hits(word: str, weights: dict, known: dict) -> tuple[str, ...]:
    """The features of a word that have a weight; kept for words seen before."""
    got = known.get(word)
    if got is None:
        if len(known) > 100_000:
            known.clear()
        got = known[word] = tuple(f for f in features(word) if f in weights)
    return got


def log_clean(s: float) -> float:
    return -(s + math.log1p(math.exp(-s)) if s > 0 else math.log1p(math.exp(s)))


def doc_score(model: dict, text: str | None, known: dict) -> float:
    return -math.expm1(sum(log_clean(z) for _, _, z in sentence_scores(model, text or "", known)) if model["weights"] else 0.0) + 0.0


def train(docs: DataFrame, labels: DataFrame, usable=None, per_class: int = SAMPLE) -> dict:
    sample, sizes = labelled_sample(docs, labels, "toxic", F.lit(True) if usable is None else usable, per_class)
    sample = written(sample.repartition(16, "id"))
    vocabulary = vocabulary_of(sample)
    rows = [(bytes(r.feats), bytes(r.sizes), r.y) for r in bags(sample, vocabulary).toLocalIterator()]
    return fit(rows, list(vocabulary), sizes)


def annotate(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text", blame: float = 0.5) -> DataFrame:
    """Every row with score, predicted, and offending: the spans (start, end, score) of sentences from blame up.

    Spans count code points of the text (of its lower-case form in the rare case that it is longer)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
        known: dict = {}
        for b in batches:
            score, spans = [], []
            for t in b.column(1):
                total, own = 0.0, []
                for s, e, z in sentence_scores(model, t.as_py() or "", known) if model["weights"] else ():
                    total += log_clean(z)
                    if (p := -math.expm1(log_clean(z))) >= blame:
                        own.append({"start": s, "end": e, "score": p})
                score.append(-math.expm1(total) + 0.0)
                spans.append(own)
            yield batch(id=b.column(0), **{"score": pa.array(score, pa.float64()), "predicted": pa.array([int(x >= 0.5) for x in score], pa.int32()), "offending": pa.array(spans, kind)})

    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    return map_batches(rows, run, f"id {kind}, score double, predicted int, offending array<struct<start:long,end:long,score:double>>").withColumnRenamed("id", id_col)


def clean(docs: DataFrame, model: dict, text_col: str = "text", most: float = 0.5) -> DataFrame:
    """The rows that score below `most`, with all their columns: each batch is scored and filtered in place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict = {}
        at = docs_columns.index(text_col)
        for b in batches:
            yield b.filter(pa.array([doc_score(model, t.as_py(), known) < most for t in b.column(at)], pa.bool_()))

    docs_columns = docs.columns
    return map_batches(docs, run, docs.schema)


def op5_mil_toxicity(spark, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = train(docs, labels, crc("doc_id") % 5 != 0)
    out = annotate(docs, model)
    held = F.coalesce(crc("doc_id") % 5 == 0, F.lit(False))
    return out.select("doc_id", held.alias("held_out"), "score", "predicted", F.size("offending").alias("n_offending"))
