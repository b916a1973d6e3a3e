"""Token counts behind a digest cache.

Content is normalised in a way that can't change its count, digested, and joined by (content digest, tokenizer digest) to
counts stored earlier. Only distinct misses are encoded; their counts are appended to the cache. The cache is a Parquet
folder partitioned by tokenizer digest: another vocabulary file, or another version of the library, never meets old counts.

Scale: texts are shuffled once, by digest, and combined before the shuffle, so a text that makes up a third of all rows
travels once per input task. What returns to the documents is digests and counts only.

Defined results: null and empty texts count 0 tokens; texts are counted whole; repeated rows and ids each keep their row;
an empty table gives an empty result and leaves the cache as it was. Special strings inside texts are handled as the
library does by default, nothing is added, cut or padded.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .bpe_prefix import BEYOND_LATIN, LATIN_WORDS, SPACES, UNLIKE_SPACE, WORD_PATTERN

CACHE = "digest binary, n_tokens bigint, tokenizer string"


class Counter:
    """Counts by the library; for vocabularies that drop white space, chunks between it are counted once each."""

    def __init__(self, path: str, memo_words: int = 200_000) -> None:
        self.by_word = self.latin = False
        self.memo, self.older, self.memo_words = {"": 0}, {}, memo_words
        if path.endswith(".model"):
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            self._lengths = lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
        else:
            from tokenizers import Tokenizer

            model = Tokenizer.from_file(path)
            model.no_truncation()
            model.no_padding()
            self.by_word, self.latin = drops_space(path), has_latin_words(path)
            self._lengths = lambda texts: [len(x.ids) for x in model.encode_batch_fast(texts, add_special_tokens=False)]
            if self.latin:
                self._model, end = model, model.model.end_of_word_suffix
                ids = model.get_vocab(True)
                self._ends = np.zeros(max(ids.values()) + 1, bool)
                self._ends[[i for t, i in ids.items() if t.endswith(end)]] = True

    def _word_lengths(self, words: list[str]) -> list[int]:
        """Of words of the pattern: one text of many words, told apart by the tokens that end words."""
        out: list[int] = []
        for start in range(0, len(words), 1024):
            some = words[start : start + 1024]
            ids = np.array(self._model.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids)
            at = np.flatnonzero(self._ends[ids])
            out += np.diff(at, prepend=-1).tolist() if len(at) == len(some) else self._lengths(some)
        return out

    def _learn(self, texts: set[str], words: bool = False) -> None:
        """Put counts of new chunks or words into the memo."""
        memo, older = self.memo, self.older
        new = []
        for t in texts:
            known = older.get(t)
            if known is None:
                new.append(t)
            else:
                memo[t] = known
        for start in range(0, len(new), 4096):
            some = new[start : start + 4096]
            memo.update(zip(some, (self._word_lengths if words else self._lengths)(some), strict=True))

    def lengths(self, texts: list[str]) -> list[int]:
        if not self.by_word:
            return self._lengths(texts) if texts else []
        if len(self.memo) > self.memo_words:
            self.memo, self.older = {"": 0}, self.memo
        memo = self.memo
        chunks = [SPACES.split(t) if UNLIKE_SPACE.search(t) else t.split() for t in texts]
        new = {c for row in chunks for c in row if c not in memo}
        if self.latin:  # a chunk's count is the sum of its words', and words are fewer than chunks
            parts = {c: LATIN_WORDS.findall(c.lower()) for c in new if "<|" not in c and BEYOND_LATIN.search(c) is None}
            self._learn({c for c in new if c not in parts})
            self._learn({w for own in parts.values() for w in own if w not in memo}, True)
            for c, own in parts.items():
                memo[c] = sum(map(memo.__getitem__, own))
        else:
            self._learn(new)
        return [sum(map(memo.__getitem__, row)) for row in chunks]


def has_latin_words(path: str) -> bool:
    """Whether the file's word pattern is the one that ``LATIN_WORDS`` stands for, after lower-casing."""
    import json

    spec = json.load(open(path, encoding="utf-8"))
    first = ((spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0]
    steps = [n["type"] for n in (spec.get("normalizer") or {}).get("normalizers", [])]
    return drops_space(path) and first["pattern"].get("Regex") == WORD_PATTERN and steps == ["NFC", "Replace", "Lowercase"]


def drops_space(path: str) -> bool:
    """Whether no token and no rule of the vocabulary file reaches over white space, so that chunks can be counted alone."""
    import json

    spec = json.load(open(path, encoding="utf-8"))
    rule = spec.get("pre_tokenizer") or {}
    first = (rule.get("pretokenizers") or [rule])[0]
    alone = not any(any(c.isspace() for c in x["content"]) or x["lstrip"] or x["rstrip"] or x["single_word"] for x in spec["added_tokens"])
    return alone and spec.get("post_processor") is None and first.get("type") == "Split" and first["invert"] and first["behavior"] == "Removed" and r"[^\s" in first["pattern"].get("Regex", "")


@lru_cache(maxsize=4)
def counter(path: str) -> Counter:
    return Counter(path)


def tokenizer_digest(path: str) -> str:
    """Of the vocabulary file and the version of the library that reads it."""
    import sentencepiece
    import tokenizers

    library = f"sentencepiece {sentencepiece.__version__}" if path.endswith(".model") else f"tokenizers {tokenizers.__version__}"
    with open(path, "rb") as f:
        return hashlib.sha256(library.encode() + b"\0" + f.read()).hexdigest()


def normalised(text: Column, path: str) -> Column:
    """White-space vocabularies: tabs and line ends become blanks, blanks at the ends go. Others: the text as it is."""
    text = F.coalesce(text, F.lit(""))
    if path.endswith(".model") or not drops_space(path):
        return text
    return F.trim(F.translate(text, "\t\n\r", "   "))


def count_tokens(docs: DataFrame, path: str, cache: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """id, n_bytes (UTF-8) and n_tokens per row of ``docs``; ``cache`` is the folder of stored counts."""
    spark = docs.sparkSession
    version = tokenizer_digest(path)
    content = normalised(F.col(f"`{text}`"), path)
    keyed = docs.select(F.col(f"`{id_col}`"), F.coalesce(F.octet_length(F.col(f"`{text}`")), F.lit(0)).cast("long").alias("n_bytes"), F.unhex(F.sha2(content, 256)).alias("digest"), content.alias("content"))
    distinct = keyed.groupBy("digest").agg(F.first("content").alias("content"))
    missed = distinct.join(_stored(spark, cache, version), "digest", "left_anti")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(path)
        for part in common.pieces(batches, 1):
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(count.lengths(common.texts_of(part.column(1))), pa.int64())], names=["digest", "n_tokens"])

    missed.mapInArrow(run, "digest binary, n_tokens bigint").withColumn("tokenizer", F.lit(version)).write.mode("append").partitionBy("tokenizer").parquet(cache)
    return keyed.drop("content").join(_stored(spark, cache, version), "digest", "left").select(id_col, "n_bytes", "n_tokens")


def _stored(spark: SparkSession, cache: str, version: str) -> DataFrame:
    """One row per digest, also where two jobs have appended the same one."""
    try:
        rows = spark.read.schema(CACHE).parquet(cache)
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        rows = spark.createDataFrame([], CACHE)
    return rows.where(F.col("tokenizer") == version).groupBy("digest").agg(F.max("n_tokens").alias("n_tokens"))


def op2_token_cache(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every document; the cache starts empty, so each distinct text is encoded in this call."""
    import public_tokenizers

    docs = common.table(spark, sf_dir, "documents")
    out = count_tokens(docs, public_tokenizers.path("word_bpe_49k.json"), common.shared_dir(spark, "token-cache"))
    return out.withColumn("over_limit", F.col("n_tokens") > 2048)
