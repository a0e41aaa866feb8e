"""Quality by positive-unlabelled learning: the non-negative unbiased risk of trusted positives and unlabelled text.

A small network on text statistics minimises  prior * R_p(+) + max(0, R_u(-) - prior * R_p(-)),  where R_p and R_u
are mean losses over trusted good documents and over unlabelled ones; where the bracket would turn negative its
gradient is reversed. The class prior is estimated first: a classifier of trusted against unlabelled documents
ranks both on rows that it hasn't seen, and the least ratio of the shares above a threshold (with a margin for
small counts) bounds the share of good documents among the unlabelled.

Inputs are statistics of the text alone (letters, symbols, words, lines, repetition, zstandard ratio), computed once
for every row and written.
Fit: at most SAMPLE trusted and SAMPLE unlabelled rows (those with the smallest hash of their id). The prior and the
logit called even are taken from all rows, as histograms of their logits with STEPS cells a unit: of all trusted rows
and of all rows of the table. The classifier behind the prior is fitted twice, to either half of the sampled ids, and
ranks the rows of the other half.

Nulls and ties: a null text is an empty one and is scored; a null label is no label; an id labelled twice is
trusted if all its rows say good; repeated rows are scored each; without trusted documents every score is 0.5.
An empty table gives no rows. Other columns are not read. Texts are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, crc, map_batches, table, written

SAMPLE = 8000
HIDDEN = 24
STEPS, REACH = 64, 40  # histograms of logits: cells a unit, largest logit told apart
CLASSES = {"upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", "lower": b"abcdefghijklmnopqrstuvwxyz", "digit": b"0123456789", "blank": b" \t", "line": b"\n", "stop": b".", "comma": b",;:", "shout": b"!?", "mark": b"#*$%&^~+=@", "bar": b"|<>{}[]\\/_", "quote": b"\"'`()-"}
NAMES = [*CLASSES, "wide", "words", "word_length", "distinct", "short", "capital", "shouted", "marked", "line_length", "same_lines", "pairs", "ratio", "symbols_at_end", "longest", "again"]


def statistics(text: str, squeeze: zstandard.ZstdCompressor) -> list[float]:
    raw = text.encode()
    n = max(len(raw), 1)
    count = np.bincount(np.frombuffer(raw, np.uint8), minlength=256) if raw else np.zeros(256)
    out = [float(count[list(c)].sum()) / n for c in CLASSES.values()]
    words = raw.split()
    k = max(len(words), 1)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    pairs = set(zip(words, words[1:]))
    lengths = np.fromiter(map(len, words), np.int64, len(words)) if words else np.zeros(1, np.int64)
    out += [
        float(count[128:].sum()) / n,
        np.log1p(len(words)) / 10,
        float(lengths.mean()) / 20,
        len(set(words)) / k,
        float((lengths <= 3).mean()),
        sum(map(bytes.istitle, words)) / k,
        sum(map(bytes.isupper, words)) / k,
        sum(not w.isalnum() and w.isascii() for w in words) / k,
        np.log1p(len(raw) / max(len(lines), 1)) / 10,
        1 - len(set(lines)) / max(len(lines), 1),
        len(pairs) / max(len(words) - 1, 1),
        min(len(squeeze.compress(raw)) / n, 1.5) if raw else 1.5,
        sum(w[-1] in b"#*$%&|!<>" for w in words) / k,
        np.log1p(float(lengths.max())) / 10,
        sum(map(bytes.__eq__, words, words[1:])) / k,
    ]
    return out


def featured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, half (by a hash of the id) and the statistics packed as float32."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze = zstandard.ZstdCompressor(level=1)
        for b in batches:
            made = [np.array(statistics(t.as_py() or "", squeeze), "<f4").tobytes() for t in b.column(2)]
            yield batch(id=b.column(0), half=b.column(1), x=pa.array(made, pa.binary()))

    key = F.col(id_col)
    rows = docs.select(key.alias("id"), F.xxhash64(key, F.lit(11)).bitwiseAND(1).cast("int").alias("half"), F.col(text_col).alias("text"))
    return map_batches(rows, run, f"id {docs.schema[id_col].dataType.simpleString()}, half int, x binary")


def unpacked(x: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(x.to_pylist()), "<f4").astype(float).reshape(-1, len(NAMES))


class Net:
    """One hidden layer of tanh units on standardised inputs, fitted by Adam."""

    def __init__(self, x: np.ndarray, seed: int = 3):
        r = np.random.default_rng(seed)
        self.mean, self.scale = x.mean(0), x.std(0) + 1e-3
        self.w = [r.normal(0, 0.3, (x.shape[1], HIDDEN)), np.zeros(HIDDEN), r.normal(0, 0.3, HIDDEN), np.zeros(1)]
        self.m, self.v, self.k = [np.zeros_like(a) for a in self.w], [np.zeros_like(a) for a in self.w], 0

    def inputs(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -6, 6)

    def logits(self, x: np.ndarray) -> np.ndarray:
        a, b, c, d = self.w
        return np.tanh(self.inputs(x) @ a + b) @ c + d[0]

    def step(self, x: np.ndarray, slope: np.ndarray, rate: float) -> None:
        """Move against slope, the gradient of the risk in each row's logit."""
        a, b, c, _ = self.w
        z = self.inputs(x)
        h = np.tanh(z @ a + b)
        back = slope[:, None] * c * (1 - h * h)
        grads = [z.T @ back, back.sum(0), h.T @ slope, np.array([slope.sum()])]
        self.k += 1
        for i, g in enumerate(grads):
            g = g + 1e-4 * self.w[i]
            self.m[i], self.v[i] = 0.9 * self.m[i] + 0.1 * g, 0.999 * self.v[i] + 0.001 * g * g
            self.w[i] = self.w[i] - rate * (self.m[i] / (1 - 0.9**self.k)) / (np.sqrt(self.v[i] / (1 - 0.999**self.k)) + 1e-8)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def batches_of(n: int, size: int, r: np.random.Generator) -> Iterator[np.ndarray]:
    order = r.permutation(n)
    for k in range(0, n, size):
        yield order[k : k + size]


def ranker(pos: np.ndarray, unl: np.ndarray, rounds: int = 30, seed: int = 5) -> Net | None:
    """A classifier of trusted against unlabelled documents; None for fewer than 5 of either."""
    if min(len(pos), len(unl)) < 5:
        return None
    x, y = np.r_[pos, unl], np.r_[np.ones(len(pos)), np.zeros(len(unl))]
    w = np.where(y > 0, 0.5 / len(pos), 0.5 / len(unl)) * len(y)
    r, net = np.random.default_rng(seed), Net(x)
    for _ in range(rounds):
        for k in batches_of(len(y), 256, r):
            net.step(x[k], w[k] * (sigmoid(net.logits(x[k])) - y[k]) / len(k), 0.003)
    return net


def cells(z: np.ndarray) -> np.ndarray:
    return (np.floor(np.clip(z, -REACH, REACH) * STEPS) + REACH * STEPS).astype(np.int64)


def histogram(cell: np.ndarray, n: np.ndarray | None = None) -> np.ndarray:
    return np.bincount(cell, n, 2 * REACH * STEPS + 1)


def quantile(h: np.ndarray, q: float) -> float:
    """The middle of the cell that the share q of all rows reaches."""
    k = int(np.searchsorted(np.cumsum(h), q * h.sum()))
    return (k + 0.5) / STEPS - REACH


def share_of_good(hp: np.ndarray, hu: np.ndarray) -> float:
    """From the ranker's histograms of trusted and of all rows: the least ratio of their shares above a threshold."""
    if not hp.sum() or not hu.sum():
        return 0.5
    qp, qu = (1 - np.r_[0, np.cumsum(h)[:-1]] / h.sum() for h in (hp, hu))
    margin = np.sqrt(np.log(40) / 2 / hp.sum()) + np.sqrt(np.log(40) / 2 / hu.sum())
    best = int(np.argmin(np.where(qp >= 0.02, (qu + margin) / np.maximum(qp, 1e-9), np.inf)))
    return float(np.clip(qu[best] / qp[best], 0.02, 0.98))


def class_prior(pos: np.ndarray, unl: np.ndarray, seed: int = 5) -> float:
    """Share of good among unlabelled documents held in memory."""
    r = np.random.default_rng(seed)
    halves = [[x[k::2] for k in (0, 1)] for x in (r.permutation(pos), r.permutation(unl))]
    nets = [ranker(halves[0][k], halves[1][k]) for k in (1, 0)]  # each half is ranked by the other's
    if None in nets:
        return 0.5
    return share_of_good(*(sum(histogram(cells(net.logits(x))) for net, x in zip(nets, h)) for h in halves))


def fit(pos: np.ndarray, unl: np.ndarray, prior: float | None = None, rounds: int = 60, rate: float = 0.004, seed: int = 7) -> dict:
    """Non-negative PU risk minimisation with the logistic loss."""
    if not len(pos) or not len(unl):
        return {"net": None, "prior": prior, "cut": 0.0}
    prior = class_prior(pos, unl) if prior is None else prior
    r, net = np.random.default_rng(seed), Net(np.r_[pos, unl])
    steps = max(1, max(len(pos), len(unl)) // 512)
    for _ in range(rounds):
        for _ in range(steps):
            p, u = pos[r.integers(0, len(pos), 512)], unl[r.integers(0, len(unl), 512)]
            zp, zu = net.logits(p), net.logits(u)
            negative = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
            gp, gu = -prior * sigmoid(zp) / len(zp), sigmoid(zu) / len(zu)  # of the bracket
            if negative >= 0:
                net.step(np.r_[p, u], np.r_[gp - prior * sigmoid(-zp) / len(zp), gu], rate)
            else:
                net.step(np.r_[p, u], -np.r_[gp, gu], rate)
    return {"net": net, "prior": prior, "cut": cut_between(histogram(cells(net.logits(pos))), histogram(cells(net.logits(unl))), prior)}


def cut_between(hp: np.ndarray, hu: np.ndarray, prior: float) -> float:
    """The logit to call even, from histograms of the logits of trusted and of all rows. Clipping the risk at zero stops
    small groups of bad texts short of it, so it is placed midway between the lowest trusted documents and the top of
    the share of unlabelled ones that the prior leaves."""
    if not hp.sum() or not hu.sum():
        return 0.0
    low_good, high_bad = quantile(hp, 0.002), quantile(hu, max(0.0, 1 - prior - 0.01))
    return float(max(0.0, (low_good + high_bad) / 2)) if low_good > high_bad else 0.0


def counted(feats: DataFrame, good: DataFrame, nets: list[Net]) -> tuple[np.ndarray, np.ndarray]:
    """Histograms of the logits of all trusted rows and of all rows, each row by the net of its half. Rows are counted
    by cell, trusted ones by id and cell, before they are shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, half = unpacked(b.column(2)), b.column(1).to_numpy()
            yield batch(id=b.column(0), cell=pa.array(cells(np.where(half == 0, nets[0].logits(x), nets[1].logits(x)))))

    rows = map_batches(feats, run, f"id {feats.schema['id'].dataType.simpleString()}, cell long")
    trusted = rows.groupBy("id", "cell").agg(F.count("*").alias("n")).join(good, "id", "left_semi")

    def of(per_cell: DataFrame) -> np.ndarray:  # as many rows as cells
        got = per_cell.toPandas()
        return histogram(got["cell"].to_numpy(np.int64), got["n"].to_numpy(np.int64))

    return of(trusted.groupBy("cell").agg(F.sum("n").alias("n"))), of(rows.groupBy("cell").agg(F.count("*").alias("n")))


def lowest(rows: DataFrame, sample: int, seed: int, *ties: str) -> DataFrame:
    """At most `sample` rows, those with the smallest hash of their id. A bound on the hash, four times too high, spares
    the sort most rows of a large table."""
    n = rows.count()
    place = F.xxhash64("id", F.lit(seed)).bitwiseAND((1 << 62) - 1)
    most = (1 << 62) * 4 * sample // max(n, 4 * sample)
    return rows.where(place < F.lit(most)).orderBy(place, "id", *ties).limit(sample)


def train(docs: DataFrame, labels: DataFrame, usable=None, sample: int = SAMPLE, prior: float | None = None) -> dict:
    """fitted() of texts that have no statistics yet."""
    return fitted(written(featured(docs)), labels, usable, sample, prior)


def fitted(feats: DataFrame, labels: DataFrame, usable=None, sample: int = SAMPLE, prior: float | None = None) -> dict:
    """From written statistics (featured) and labels. Trusted: usable rows labelled good. Unlabelled: any rows, drawn
    whatever their label says."""
    good = labels.where(F.lit(True) if usable is None else usable).where(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("q")).where("q = 1")
    good = written(good.select(F.col("doc_id").cast(feats.schema["id"].dataType).alias("id")))
    some = F.broadcast(lowest(good, sample, 5))  # at most `sample` ids, and then rows
    halves, x = [], []
    for rows, seed in ((feats.join(some, "id", "left_semi"), 5), (feats.where("id IS NOT NULL"), 9)):
        got = lowest(rows, sample, seed, "x").select("half", "x").toArrow()
        halves.append(got.column(0).to_numpy())
        x.append(unpacked(got.column(1)))
    if prior is None and min(map(len, x)):
        nets = [ranker(*(m[h == k] for m, h in zip(x, halves))) for k in (1, 0)]
        prior = 0.5 if None in nets else share_of_good(*counted(feats, good, nets))
    model = fit(*x, prior)
    if model["net"]:
        model["cut"] = cut_between(*counted(feats, good, [model["net"]] * 2), prior)
    return model


def judged(feats: DataFrame, model: dict, id_col: str = "doc_id") -> DataFrame:
    """Every row's id, score and predicted, from its statistics."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = model["net"]
        for b in batches:
            p = sigmoid(net.logits(unpacked(b.column(2))) - model["cut"]) if net and b.num_rows else np.full(b.num_rows, 0.5)
            yield batch(id=b.column(0), score=pa.array(p), predicted=pa.array((p >= 0.5).astype(np.int32)))

    kind = feats.schema["id"].dataType.simpleString()
    return map_batches(feats, run, f"id {kind}, score double, predicted int").withColumnRenamed("id", id_col)


def score(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """judged() of texts that have no statistics yet."""
    return judged(featured(docs, id_col, text_col), model, id_col)


def op7_pu_quality(spark, sf_dir: str) -> DataFrame:
    feats, labels = written(featured(table(spark, sf_dir, "documents"))), table(spark, sf_dir, "labels")
    model = fitted(feats, labels, crc("doc_id") % 3 != 1)
    held = F.coalesce(crc("doc_id") % 3 == 1, F.lit(False))
    return judged(feats, model).select("doc_id", held.alias("held_out"), "score", "predicted")
