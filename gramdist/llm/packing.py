"""Packing by power-of-two decomposition: a document is split into pieces of binary lengths, and pieces of equal
length share a bucket; each piece is a sequence of its own, so none crosses documents and none is padded.

A document of n ids gives n // max_len pieces of max_len and one piece for every set bit of the rest, long pieces
first. Sequence ids number a bucket's pieces: (log2 of the length, partition, running number), so no shuffle is
needed and a retried task gives the same ids (its input must be replayable, as a table is).

Nulls and ties: a null or empty text is one piece with the end id alone; repeated rows are packed each; a null id
is carried. An empty table gives no rows. Other columns are not read. Texts are encoded whole.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, map_batches, table

END = 1
LONG_RUN = 50_000  # blanks in a row that the faster engine is spared; it held 700,000 and overflowed at 1,000,000
# Fixed value: how byte-level vocabularies of this kind cut a text before merging.
CUT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def byte_letters() -> dict[str, int]:
    """The letter that a byte-level vocabulary writes for each byte: printable Latin-1 as is, others from 256 on."""
    plain = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


@lru_cache(maxsize=4)
def encoder(path: str):
    """text -> ids of the tokenizer file. A plain byte-level BPE is run by a faster engine with the same ranks;
    its ids are the same (tests hold them together). Any other file is run as it is, and so is a text with a very
    long run of blanks, which the faster engine's stack can't hold."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
    plain = model.get("type") == "BPE" and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
    plain = plain and not spec.get("normalizer") and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges", "byte_fallback"))
    special = {t["content"]: t["id"] for t in spec.get("added_tokens") or []}
    plain = plain and not any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") or t.get("normalized") and not t.get("special") for t in spec.get("added_tokens") or [])
    from tokenizers import Tokenizer

    if not plain:
        tokenizer = Tokenizer.from_file(path)
        return lambda text: tokenizer.encode(text, add_special_tokens=False).ids
    import tiktoken

    plain_engine: list = []

    def whole(text: str) -> list[int]:
        if not plain_engine:
            plain_engine.append(Tokenizer.from_file(path))
        return plain_engine[0].encode(text, add_special_tokens=False).ids

    letters = byte_letters()
    ranks = {bytes(letters[c] for c in word): k for word, k in model["vocab"].items() if word not in special}
    fast = tiktoken.Encoding("byte-level", pat_str=CUT, mergeable_ranks=ranks, special_tokens=special)
    every = set(special)

    def encode(text: str) -> list[int]:
        if len(text) >= LONG_RUN and any(m.end() - m.start() >= LONG_RUN for m in re.finditer(r"\s+", text)):
            return whole(text)
        return fast.encode(text, allowed_special=every) if any(s in text for s in every) else fast.encode_ordinary(text)

    return encode


def cut(n: int, most: int) -> list[int]:
    """Lengths of the pieces of n ids."""
    rest = n % most
    return [most] * (n // most) + [1 << k for k in reversed(range(rest.bit_length())) if rest >> k & 1]


def pack(df: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", max_len: int = 2048, end: int = END, with_ids: bool = False) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset, bucket (and its ids)."""
    if max_len < 1 or max_len & (max_len - 1):
        raise ValueError("max_len must be a power of two")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = encoder(tokenizer), TaskContext.get().partitionId()
        made = [0] * max_len.bit_length()
        for b in batches:
            cols: dict[str, list] = {k: [] for k in ("row", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "ids")}
            for row, text in enumerate(b.column(1)):
                ids = np.array([*encode(text.as_py() or ""), end], dtype="<u4")
                at = 0
                for n in cut(len(ids), max_len):
                    k = n.bit_length() - 1
                    piece = ids[at : at + n]
                    for name, v in zip(cols, (row, at, n, zlib.crc32(piece.tobytes()), len(ids), k << 58 | part << 32 | made[k], piece if with_ids else None)):
                        cols[name].append(v)
                    made[k] += 1
                    at += n
                if len(cols["row"]) >= 50_000:
                    yield out(b, cols)
                    cols = {k: [] for k in cols}
            yield out(b, cols)

    def out(b: pa.RecordBatch, cols: dict[str, list]) -> pa.RecordBatch:
        n = len(cols["row"])
        made = {k: pa.array(cols[k], pa.int64()) for k in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id")}
        made = {"id": b.column(0).take(pa.array(cols["row"], pa.int64()))} | made | {"offset": pa.array(np.zeros(n, np.int64)), "bucket": made["length"]}
        if with_ids:
            made["ids"] = pa.array(cols["ids"], pa.list_(pa.int32()))
        return batch(**made)

    kind = df.schema[id_col].dataType.simpleString()
    schema = f"id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, bucket long" + ", ids array<int>" * with_ids
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    return map_batches(rows, run, schema).withColumnRenamed("id", id_col)


def default_tokenizer() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def op3_pack_binary(spark, sf_dir: str, tokenizer: str | None = None) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), tokenizer or default_tokenizer())
