"""Token ids by the public tokenizers, word by word with a bounded cache, and delta-maintained token totals."""

from __future__ import annotations

import json
import re
import unicodedata
from array import array
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .caches import claim
from .common import scratch

WORD_BPE = "word_bpe_49k.json"
#: Words in each of the two generations of a worker's cache. When the young one is full it becomes the old one; a word met
#: again comes back from there, so frequent words stay. The size costs time or memory and changes no id.
CACHE_WORDS = 300_000


def tokenizer_path(name: str = WORD_BPE) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


# Fixed value: the pattern by which the word tokenizer's file parts words; other files go without the short way.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Letters, then ASCII marks other than the apostrophe that contractions start with.
PLAIN = re.compile(r"([^\W\d_]+)([!-&(-/:-@\[-`{-~]*)")


def piece_encoder(path: str):
    """ids of one run of letters or marks (UTF-8, lower case), by the same merges in a faster library; None if the file is of another kind."""
    with open(path, encoding="utf-8") as f:
        file = json.load(f)
    model, before = file["model"], json.dumps([file.get("normalizer"), file.get("pre_tokenizer")])
    if model.get("type") != "BPE" or model.get("end_of_word_suffix") != "</w>" or json.dumps(WORD_PATTERN) not in before or not all(f'"{x}"' in before for x in ("NFC", "Lowercase", "ByteLevel")):
        return None
    import tiktoken

    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}
    ranks = {}
    for token, i in model["vocab"].items():
        ended = token.endswith("</w>")
        core = token[:-4] if ended else token
        if all(c in byte for c in core) and not (token.startswith("<|") and token.endswith("|>")):
            ranks[bytes(byte[c] for c in core) + (b"\xff" if ended else b"")] = i  # no UTF-8 text has this byte
    bpe = tiktoken.Encoding("words", pat_str=".+", mergeable_ranks=ranks, special_tokens={})._core_bpe
    return lambda piece: bpe.encode_single_piece(piece + b"\xff")


class _Words(dict):
    """word -> ids; a word that is not there is looked up in the old generation or encoded."""

    def __init__(self, learn):
        super().__init__()
        self.learn = learn

    def __missing__(self, word: bytes) -> bytes:
        ids = self[word] = self.learn(word)
        return ids


class WordIds:
    """Ids of whole texts as little-endian unsigned 32-bit bytes.

    The word tokenizer never joins characters across white space and knows no capitals: a text's ids are the ids of
    its ASCII-space-parted words in order, so each distinct word is encoded once and looked up afterwards.
    Any other file's tokenizer encodes whole texts.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.path, self.piece = path, piece_encoder(path)
        self._forget()

    def _forget(self) -> None:
        self.young, self.old = _Words(self._learn), {}

    def _learn(self, word: bytes) -> bytes:
        ids = self.old.get(word)
        if ids is None:
            ids = self._plain(word)
        if ids is None:
            ids = array("I", self.tokenizer.encode(word.decode("utf-8"), add_special_tokens=False).ids).tobytes()
        return ids

    def _plain(self, word: bytes) -> bytes | None:
        """Ids of a word of letters, maybe with marks after them, whose form is sure to be kept; None for any other."""
        if word.isalpha():
            return array("I", self.piece(word)).tobytes()
        text = word.decode("utf-8")
        m = PLAIN.fullmatch(text)
        if m is None or not m[1].isalpha() or "\u03a3" in text or not unicodedata.is_normalized("NFC", text):
            return None
        letters = m[1].lower()
        if not letters.isalpha():
            return None
        ids = self.piece(letters.encode())
        return array("I", ids + self.piece(m[2].encode()) if m[2] else ids).tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        if self.piece is None:
            return [array("I", self.tokenizer.encode(t, add_special_tokens=False).ids).tobytes() if t else b"" for t in texts]
        claim(f"ids of {self.path}", self._forget)
        out = []
        for t in texts:
            if len(self.young) > CACHE_WORDS:
                self.old, self.young = self.young, _Words(self._learn)
            out.append(b"".join(map(self.young.__getitem__, t.encode("utf-8", "replace").lower().split())) if t else b"")
        return out


@lru_cache(4)
def word_ids(path: str) -> WordIds:
    """One per Python worker and file."""
    return WordIds(path)


def token_counts(docs: DataFrame, path: str, version: str) -> DataFrame:
    """doc_id, source, lang, tokenizer, n_tokens. A null text has no tokens; every row counts, repeated ones too."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        coder = word_ids(path)
        for b in batches:
            for at in range(0, len(b), 512):
                part = b.iloc[at : at + 512]
                yield pd.DataFrame({"doc_id": part["doc_id"], "source": part["source"], "lang": part["lang"], "tokenizer": version, "n_tokens": [len(x) // 4 for x in coder.encode(list(part["text"]))]})

    kinds = {f.name: f.dataType for f in docs.schema}
    schema = T.StructType([T.StructField(c, kinds[c]) for c in ("doc_id", "source", "lang")] + [T.StructField("tokenizer", T.StringType()), T.StructField("n_tokens", T.LongType())])
    return docs.select("doc_id", "source", "lang", "text").mapInPandas(run, schema)


def inserts(counts: DataFrame) -> DataFrame:
    """Signed rows that add documents: counts has source, lang, tokenizer, n_tokens."""
    return counts.select("source", "lang", "tokenizer", F.lit(1).cast("long").alias("sign"), "n_tokens")


def deletes(counts: DataFrame) -> DataFrame:
    """Signed rows that take documents back, with the counts they were added with."""
    return counts.select("source", "lang", "tokenizer", F.lit(-1).cast("long").alias("sign"), "n_tokens")


def revisions(old: DataFrame, new: DataFrame) -> DataFrame:
    """Signed rows that replace counts: the old ones go, the new ones come; they may differ in any column."""
    return deletes(old).unionByName(inserts(new))


class TokenTotals:
    """Additive totals by source, language and tokenizer version, kept under signed batches.

    A batch is folded to its sums by key and written as one folder named by its id; a marker is written
    last. A batch whose marker exists is not applied again, one that broke off before its marker is
    written over, so a repeated commit changes nothing. Totals are the sums over committed batches; `fold`
    puts them into one snapshot, and only later batches are read besides it. Null keys are keys of their own; a key whose documents have all gone,
    with no tokens left, is not returned.
    """

    KEYS = ("source", "lang", "tokenizer")

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or scratch(spark, "token-totals")

    def _fs(self, where: str):
        p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(where)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), p

    def committed(self) -> list[str]:
        fs, p = self._fs(f"{self.path}/committed")
        return sorted(x.getPath().getName() for x in fs.listStatus(p)) if fs.exists(p) else []

    def commit(self, batch_id: str, signed: DataFrame) -> bool:
        """Apply a batch once; False if it had been applied."""
        if "/" in batch_id or batch_id.startswith((".", "_")):
            raise ValueError("a batch id is one plain folder name")
        fs, marker = self._fs(f"{self.path}/committed/{batch_id}")
        if fs.exists(marker):
            return False
        sums = signed.groupBy(*self.KEYS).agg(F.sum("sign").alias("n_docs"), F.sum(F.col("sign") * F.coalesce(F.col("n_tokens"), F.lit(0))).alias("n_tokens"))
        sums.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/batches/{batch_id}")
        fs.create(marker, True).close()
        return True

    def _last_fold(self) -> tuple[str, list[str]]:
        """Folder of the newest snapshot and the batches it holds; a list that lacks its end mark was never finished."""
        fs, p = self._fs(f"{self.path}/folds")
        names = sorted((x.getPath().getName() for x in fs.listStatus(p)), reverse=True) if fs.exists(p) else []
        for name in names:
            stream = fs.open(self._fs(f"{self.path}/folds/{name}")[1])
            lines = self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8").split("\n")
            stream.close()
            if lines[-1] == "end":
                return lines[0], lines[1:-1]
        return "", []

    def totals(self) -> DataFrame:
        """source, lang, tokenizer, n_docs, n_tokens over the committed batches."""
        folded, held = self._last_fold()
        paths = ([folded] if folded else []) + [f"{self.path}/batches/{b}" for b in self.committed() if b not in set(held)]
        schema = "source string, lang string, tokenizer string, n_docs long, n_tokens long"
        log = self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)
        return log.groupBy(*self.KEYS).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens")).where("n_docs <> 0 or n_tokens <> 0")

    def fold(self) -> None:
        """Write the totals as one snapshot; the list of the batches it holds comes last and makes it count."""
        done, (_, held) = self.committed(), self._last_fold()
        if len(done) < 2 or set(done) == set(held):
            return
        path = scratch(self.spark, "folded-totals")
        self.totals().coalesce(1).write.parquet(path)
        fs, p = self._fs(f"{self.path}/folds")
        n = len(fs.listStatus(p)) if fs.exists(p) else 0
        out = fs.create(self._fs(f"{self.path}/folds/{n:09d}")[1], True)
        out.write(bytearray("\n".join([path, *done, "end"]).encode()))
        out.close()

