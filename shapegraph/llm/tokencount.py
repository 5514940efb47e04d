"""Token counts behind a digest cache.

Contents are keyed by SHA-256 of the normalised text and by SHA-256 of the tokenizer file. A join with the stored
counts leaves the misses; one text of each missing digest is encoded, and the new counts are appended.
"""

from __future__ import annotations

import hashlib
import json
import os
import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, fresh_path, slices, table

#: Words that a task remembers at most before it starts anew.
MEMO_WORDS = 450_000
#: Ends of words that no byte-level pre-tokenizer takes for white space, whatever its version of Unicode.
_PLAIN = "[!-~À-ÖØ-öø-ÿ]"
_WORD = re.compile(f"{_PLAIN}(?:.*{_PLAIN})?", re.DOTALL)

CACHE = "digest binary, tokenizer string, n_tokens long"


def normalised(text: Column) -> Column:
    """The content that is hashed and encoded. Byte-level counts depend on every byte, so only null becomes empty."""
    return F.coalesce(text, F.lit(""))


def tokenizer_version(path: str) -> str:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


def _encoder(path: str):
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    made = Tokenizer.from_file(path)
    made.no_truncation()
    made.no_padding()
    whole = lambda texts: [len(x) for x in made.encode_batch_fast(texts, add_special_tokens=False)]
    return WordCounts(whole) if breaks_at_spaces(path) else whole


def breaks_at_spaces(path: str) -> bool:
    """Whether a single space between two plain characters always begins a new piece, so that counts add up over it."""
    with open(path, encoding="utf-8") as f:
        data = json.load(f)
    before = data.get("pre_tokenizer") or {}
    added = all(" " not in t["content"] and not (t["lstrip"] or t["rstrip"] or t["single_word"]) for t in data.get("added_tokens", []))
    return before.get("type") == "ByteLevel" and before.get("use_regex", True) and not before.get("add_prefix_space", True) and not data.get("normalizer") and data["model"]["type"] == "BPE" and added


class WordCounts:
    """Token counts of texts as sums over their words, each with the space before it, which are encoded once and remembered.
    A word that begins or ends with other than a plain character is encoded together with its neighbours."""

    def __init__(self, whole):
        self.whole, self.memo, self.first, self.odd = whole, {}, {}, set()

    def _runs(self, words: list[str]) -> list[str]:
        """The text of ``words`` cut at the spaces between two plain words."""
        runs, start = [], 0
        for i in range(1, len(words)):
            if words[i] not in self.odd and words[i - 1] not in self.odd and _WORD.fullmatch(words[i - 1]):
                runs.append(" " * (start > 0) + " ".join(words[start:i]))
                start = i
        return [*runs, " " * (start > 0) + " ".join(words[start:])]

    def __call__(self, texts: list[str]) -> list[int]:
        if len(self.memo) + len(self.first) + len(self.odd) > MEMO_WORDS:
            self.memo, self.first, self.odd = {}, {}, set()
        split = [t.split(" ") for t in texts]
        new = {w for words in split for w in words[1:]} - self.memo.keys() - self.odd
        plain = [w for w in new if _WORD.fullmatch(w)]
        self.odd |= new.difference(plain)
        self.memo.update(zip(plain, self.whole([f" {w}" for w in plain]), strict=True))
        easy = [self.odd.isdisjoint(words[1:]) and (len(words) == 1 or bool(_WORD.fullmatch(words[0]))) for words in split]
        heads = list({words[0] for words, ok in zip(split, easy, strict=True) if ok} - self.first.keys())
        self.first.update(zip(heads, self.whole(heads), strict=True))
        runs = [[] if ok else self._runs(words) for words, ok in zip(split, easy, strict=True)]
        counted = {r[1:]: self.memo[r[1:]] for rs in runs for r in rs if r[:1] == " " and r[1:] in self.memo}
        rest = list({r for rs in runs for r in rs if not (r[:1] == " " and r[1:] in counted)})
        other = dict(zip(rest, self.whole(rest), strict=True))
        known = self.memo.__getitem__
        return [self.first[words[0]] + sum(map(known, words[1:])) if ok else sum(counted[r[1:]] if r[:1] == " " and r[1:] in counted else other[r] for r in rs) for words, ok, rs in zip(split, easy, runs, strict=True)]


def count_tokens(path: str):
    """A mapInArrow function (digest, text) -> (digest, n_tokens); the tokenizer is read on the executor."""

    def count(batches):
        encode = _encoder(path)
        for rows, texts in slices(batches):
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(encode([t.decode("utf-8") for t in texts]), pa.int64())], names=["digest", "n_tokens"])

    return count


def cached_counts(df: DataFrame, tokenizer: str, cache: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 512) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every input row; misses are encoded once and appended to ``cache``.

    Null counts as empty (0 tokens); repeated rows share one cache row; an empty table appends nothing.
    """
    spark, version = df.sparkSession, tokenizer_version(tokenizer)
    text = normalised(F.col("text"))
    keyed = documents(df, id_col, text_col).select("doc_id", F.unhex(F.sha2(text.cast("binary"), 256)).alias("digest"), text.alias("text"))

    def stored() -> DataFrame:
        return spark.read.schema(CACHE).parquet(cache).where(F.col("tokenizer") == version)

    spark.createDataFrame([], CACHE).write.mode("append").parquet(cache)
    wanted = keyed.groupBy("digest").agg(F.first("text").alias("text"))
    misses = wanted.join(stored(), "digest", "left_anti")
    fresh = misses.select("digest", "text").mapInArrow(count_tokens(tokenizer), "digest binary, n_tokens long")
    fresh.select("digest", F.lit(version).alias("tokenizer"), "n_tokens").write.mode("append").parquet(cache)
    rows = keyed.select("doc_id", "digest", F.octet_length("text").cast("long").alias("n_bytes"))
    counts = stored().dropDuplicates(["digest"]).select("digest", "n_tokens")
    return rows.join(counts, "digest").select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return cached_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), fresh_path(spark, "token-cache"))
