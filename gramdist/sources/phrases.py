"""A Spark data source of phrase files: lines "id TAB codec TAB phrase TAB phrase ..." become strings.

Phrases are a number, a colon and a letter: the letter's count for RLE ("3:a"), an earlier phrase for LZ78 ("2:b", 0
for none, the letter absent in a last repeated phrase). Backslash escapes stand for tabs, line ends and backslashes.
"""

from __future__ import annotations

import re

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

ESCAPES = {"\\t": "\t", "\\n": "\n", "\\\\": "\\"}


def plain(s: str) -> str:
    return re.sub(r"\\[tn\\]", lambda m: ESCAPES[m[0]], s)


def guarded(s: str) -> str:
    return s.replace("\\", "\\\\").replace("\t", "\\t").replace("\n", "\\n")


def encode(text: str, codec: str) -> list[str]:
    from ..functions import grammar as G

    if codec == "rle":
        return [f"{k}:{guarded(c)}" for c, k in G.runs(text)]
    out, known, now = [], {"": 0}, ""
    for c in text:
        if now + c in known:
            now += c
        else:
            out.append(f"{known[now]}:{guarded(c)}")
            known[now + c] = len(known)
            now = ""
    return out + ([f"{known[now]}:"] if now else [])


def decode(phrases: list[str], codec: str) -> str:
    made = [""]
    for p in phrases:
        number, _, letter = p.partition(":")
        made.append(plain(letter) * int(number) if codec == "rle" else made[int(number)] + plain(letter))
    return "".join(made)


class PhraseReader(DataSourceReader):
    def __init__(self, path: str, files: int):
        self.path, self.files = path, files

    def partitions(self) -> list[InputPartition]:
        import glob
        import os

        names = sorted(glob.glob(os.path.join(self.path, "*.phrases"))) if os.path.isdir(self.path) else [self.path]
        return [InputPartition(n) for n in names] or [InputPartition(None)]

    def read(self, partition: InputPartition):
        if partition.value is None:
            return
        with open(partition.value, encoding="utf-8", newline="\n") as f:
            for line in f:
                ident, codec, *phrases = line.rstrip("\n").split("\t")
                yield int(ident), codec, decode([p for p in phrases if p], codec)


class PhraseSource(DataSource):
    """spark.dataSource.register(PhraseSource); spark.read.format("slp_phrases").load(path)."""

    @classmethod
    def name(cls) -> str:
        return "slp_phrases"

    def schema(self) -> str:
        return "string_id long, codec string, text string"

    def reader(self, schema) -> DataSourceReader:
        return PhraseReader(self.options["path"], 1)
