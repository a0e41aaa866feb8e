"""Language identification by fusing evidence in one posterior.

    log P(l | page) = text + declared + suffix + host prior + constant

text: tempered naive Bayes over hashed byte trigrams, counted by language over all documents. declared and suffix:
log P(markup language | l) and log P(last label of the address | l), both from grouped sums of the text
posteriors over all pages, smoothed. Host prior: a host's mean posterior, smoothed towards its registered domain's,
that towards all pages'; a page's own share is taken out of the sums first, so it doesn't vote twice.

Plain texts have the same model with their collection as the host.

Nulls and ties: a null page or text has no text evidence, a null address no host or suffix, and the rest decides;
languages with equal posteriors go by name; a document without text or language isn't counted; repeated rows
count each. Without counted documents there is no language: lang is null. An empty table gives no rows. Extra
columns are not read. Pages are read whole.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import batch, join_groups, map_batches, table, written

BINS = 1 << 14
TEMPER = 0.15  # trigrams overlap and repeat, so their evidence counts as a part of its number
HIDDEN = re.compile(r"<!--|<(script|style|nav)\b", re.I)
CLOSING = {k: re.compile(rf"</{k}\s*>", re.I) for k in ("script", "style", "nav")}
HTML = re.compile(r"<html\b", re.I)
LANG = re.compile(r"\blang\s*=\s*[\"']?([A-Za-z]+)", re.I)
HUGE = re.compile(r"&#(?:[0-9]{8,}|[xX][0-9A-Fa-f]{7,});?")  # numbers beyond any letter
HOST = re.compile(r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)")


def page_text(page: str) -> str:
    """The page without comments, scripts, styles, navigation and tags, each a blank. Every kind of closing mark is
    looked for onwards only and never again once there is none, so the time is linear in the page whatever it holds."""
    out, at, start, none = [], 0, 0, set()
    while m := HIDDEN.search(page, start):
        start, name = m.end(), (m[1] or "").lower()
        if name in none:
            continue
        if name:
            close = CLOSING[name].search(page, m.end())
            end = close.end() if close else -1
        else:
            end = page.find("-->", m.end()) + 3 if page.find("-->", m.end()) >= 0 else -1
        if end < 0:
            none.add(name)
            continue
        out += [page[at : m.start()], " "]
        at = start = end
    page, out, at = "".join([*out, page[at:]]), [], 0
    while (i := page.find("<", at)) >= 0 and (j := page.find(">", i)) >= 0:
        out += [page[at:i], " "]
        at = j + 1
    return html.unescape(HUGE.sub("\ufffd", "".join([*out, page[at:]])))


def declared_lang(page: str) -> str:
    """The language that the first html tag with one declares; tags are read up to their end once."""
    at = 0
    while m := HTML.search(page, at):
        end = page.find(">", m.end())
        end = len(page) if end < 0 else end
        if said := LANG.search(page, m.end(), end):
            return said[1].lower()
        at = end  # what lies before has no language, so a tag that starts there has none
    return ""


def address(url: str) -> tuple[str, str, str]:
    """(host, registered domain as its last two labels, last label), empty where there is none."""
    m = HOST.match(url)
    labels = m[1].lower().rstrip(".").split(".") if m else [""]
    return ".".join(labels), ".".join(labels[-2:]), labels[-1]


def trigrams(text: str) -> np.ndarray:
    """Bins of the byte trigrams of the letters and blanks, in lower case."""
    raw = np.frombuffer(re.sub(r"[\W\d_]+", " ", f" {text.lower()} ").encode(), np.uint8).astype(np.uint32)
    if len(raw) < 3:
        return np.zeros(0, np.int64)
    key = raw[:-2] * np.uint32(0x9E3779B1) ^ raw[1:-1] * np.uint32(0x85EBCA6B) ^ raw[2:] * np.uint32(0xC2B2AE35)
    return ((key * np.uint32(0x27D4EB2F)) >> np.uint32(32 - 14)).astype(np.int64)


def train(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> dict:
    """Trigram counts by language over all documents; what comes to the driver is languages times BINS numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for b in batches:
            for lang, text in zip(b.column(0).to_pylist(), b.column(1)):
                sums.setdefault(lang, np.zeros(BINS, np.int64))
                sums[lang] += np.bincount(trigrams(text.as_py()), minlength=BINS)
        for lang, n in sums.items():
            at = np.flatnonzero(n)
            yield batch(lang=pa.array([lang] * len(at), pa.string()), bin=pa.array(at.astype(np.int32)), n=pa.array(n[at]))

    rows = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    by = map_batches(rows, run, "lang string, bin int, n long").groupBy("lang", "bin").agg(F.sum("n").alias("n"))
    counts: dict[str, np.ndarray] = {}
    for r in by.toLocalIterator():
        counts.setdefault(r.lang, np.zeros(BINS))[r.bin] = r.n
    langs = sorted(counts)
    logs = np.array([np.log((counts[k] + 0.5) / (counts[k].sum() + 0.5 * BINS)) for k in langs]).reshape(len(langs), BINS)
    return {"langs": langs, "logs": logs.astype(np.float32)}


def text_evidence(model: dict, text: str) -> np.ndarray:
    n = np.bincount(trigrams(text), minlength=BINS)
    at = np.flatnonzero(n)
    z = TEMPER * (model["logs"][:, at].astype(float) @ n[at])
    return z - z.max() if len(z) else z


def evidence(pages: DataFrame, model: dict, id_col: str, url_col: str, html_col: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for url, page in zip(b.column(1), b.column(2)):
                page = page.as_py() or ""
                z = text_evidence(model, page_text(page))
                rows.append((*address(url.as_py() or ""), declared_lang(page), z.tolist()))
            cols = list(zip(*rows)) if rows else [()] * 5
            s = pa.string()
            yield batch(id=b.column(0), host=pa.array(cols[0], s), domain=pa.array(cols[1], s), suffix=pa.array(cols[2], s), declared=pa.array(cols[3], s), z=pa.array(list(cols[4]), pa.list_(pa.float64())))

    kind = pages.schema[id_col].dataType.simpleString()
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    return map_batches(rows, run, f"id {kind}, host string, domain string, suffix string, declared string, z array<double>")


def text_rows(docs: DataFrame, model: dict, id_col: str, text_col: str, host_col: str) -> DataFrame:
    """Evidence of plain texts: a collection stands for the host; there is no markup and no address."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            z = [text_evidence(model, t.as_py() or "").tolist() for t in b.column(2)]
            yield batch(id=b.column(0), host=b.column(1), z=pa.array(z, pa.list_(pa.float64())))

    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(host_col), F.lit("")).alias("host"), F.col(text_col).alias("text"))
    out = map_batches(rows, run, f"id {kind}, host string, z array<double>")
    none = F.lit("")
    return out.select("id", "host", none.alias("domain"), none.alias("suffix"), none.alias("declared"), "z")


def softmax(z: str) -> Column:
    top = f"transform({z}, x -> exp(x - array_max({z})))"
    return F.expr(f"transform({top}, x -> x / aggregate({top}, 0.0D, (a, y) -> a + y))")


def sums(k: int, name: str) -> list[Column]:
    return [F.array(*[F.sum(F.col("p")[i]) for i in range(k)]).alias(name), F.count("*").alias(f"n_{name}")]


def added(k: int, part: str, name: str) -> list[Column]:
    return [F.array(*[F.coalesce(F.sum(F.col(part)[i]), F.lit(0.0)) for i in range(k)]).alias(name), F.coalesce(F.sum(f"n_{part}"), F.lit(0)).alias(f"n_{name}")]


def fused(pages: DataFrame, model: dict, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", kappa: float = 5.0, alpha: float = 1.0) -> DataFrame:
    """One row per page: lang, probability, the language of the text alone, declared language, host and suffix."""
    return weighed(evidence(pages, model, id_col, url_col, html_col), model, id_col, kappa, alpha)


def fused_texts(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", kappa: float = 5.0) -> DataFrame:
    """The same for plain texts, with the prior of their collection."""
    return weighed(text_rows(docs, model, id_col, text_col, host_col), model, id_col, kappa, 1.0)


def weighed(rows: DataFrame, model: dict, id_col: str, kappa: float, alpha: float) -> DataFrame:
    """Posteriors from rows of evidence (id, host, domain, suffix, declared, z)."""
    k = len(model["langs"])
    if not k:
        nothing = F.lit(None)
        return rows.select(F.col("id").alias(id_col), nothing.cast("string").alias("lang"), nothing.cast("double").alias("probability"), nothing.cast("string").alias("text_lang"), "declared", "host", "suffix")
    rows = written(rows.withColumn("p", softmax("z")))
    total = rows.count()
    # a host has one domain and one suffix, so their sums come from the hosts' and are joined to hosts, not to rows
    hosts = written(rows.groupBy("host", "domain", "suffix").agg(*sums(k, "in_host")))
    every = written(hosts.agg(*added(k, "in_host", "all")))
    domains = written(hosts.groupBy("domain").agg(*added(k, "in_host", "in_domain"), F.count("*").alias("_hosts")))
    suffixes = hosts.groupBy("suffix").agg(*added(k, "in_host", "s"), F.count("*").alias("_hosts"))
    said = rows.groupBy("declared").agg(*sums(k, "s"))

    def likelihood(by: DataFrame, name: str) -> DataFrame:
        """Of what a page declares or of its suffix: smoothed shares of each language's soft count."""
        by = written(by)
        kinds = by.count()
        shares = by.crossJoin(F.broadcast(every.select("all")))  # every: one row
        return written(shares.withColumn(f"l_{name}", F.expr(f"zip_with(s, all, (a, b) -> ln((a + {alpha}) / (b + {alpha * max(kinds, 1)})))")).drop("s", "all"))

    n_hosts = hosts.count()
    hosts = written(join_groups(hosts, domains, "domain", "_hosts", n_hosts).drop("_hosts"))
    hosts = written(join_groups(hosts, likelihood(suffixes, "suffix"), "suffix", "_hosts", n_hosts).drop("_hosts", "n_s"))
    out = join_groups(rows, likelihood(said, "declared"), "declared", "n_s", total).drop("n_s")
    out = join_groups(written(out), hosts.drop("domain", "suffix"), "host", "n_in_host", total).crossJoin(F.broadcast(every))
    # each level without the page itself, smoothed by kappa pages of the level above
    out = out.withColumn("g", F.expr(f"transform(sequence(0, {k - 1}), i -> (all[i] - p[i] + 1) / (n_all - 1 + {k}))"))
    out = out.withColumn("d", F.expr(f"transform(sequence(0, {k - 1}), i -> (in_domain[i] - p[i] + {kappa} * g[i]) / (n_in_domain - 1 + {kappa}))"))
    out = out.withColumn("h", F.expr(f"transform(sequence(0, {k - 1}), i -> (in_host[i] - p[i] + {kappa} * d[i]) / (n_in_host - 1 + {kappa}))"))
    heard = "CASE WHEN declared = '' THEN 0.0D ELSE l_declared[i] END + CASE WHEN suffix = '' THEN 0.0D ELSE l_suffix[i] END"
    out = out.withColumn("z2", F.expr(f"transform(sequence(0, {k - 1}), i -> z[i] + {heard} + ln(greatest(CASE WHEN host = '' THEN g[i] ELSE h[i] END, 1e-12D)))"))
    out = out.withColumn("post", softmax("z2"))
    names = F.array(*[F.lit(x) for x in model["langs"]])
    first = lambda c: names[F.array_position(c, F.array_max(c)).cast("int") - 1]
    return out.select(F.col("id").alias(id_col), first(F.col("post")).alias("lang"), F.array_max("post").alias("probability"), first(F.col("p")).alias("text_lang"), "declared", "host", "suffix")


def op10_lang_fusion(spark, sf_dir: str) -> DataFrame:
    """All pages (page_id) and all documents (doc_id)."""
    docs = table(spark, sf_dir, "documents")
    model = train(docs)
    none = F.lit(None).cast("long")
    pages = fused(table(spark, sf_dir, "pages"), model).withColumn("doc_id", none)
    return fused_texts(docs, model).withColumn("page_id", none).unionByName(pages)
