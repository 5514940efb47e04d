"""Quality rules by weak supervision.

Rules vote good (+1), bad (-1) or abstain (0) on each document. Expectation-maximisation over the table of distinct
vote vectors (at most 3**rules rows, whatever the corpus holds) estimates how often each rule votes each way on good
and on bad documents; the posterior probability of good replaces an all-must-pass filter.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from .common import column, cut, documents, slices, table

FEATURES = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long, n_letters long, n_upper long, n_bang long"
_ARROW = pa.schema([(part.split()[0], pa.int64()) for part in FEATURES.split(", ")])

_SPACES = np.frombuffer(b" \t\n\x0b\x0c\r", np.uint8)
_SYMBOLS = np.frombuffer(b"#*$%&|<>", np.uint8)


def measure(raw: bytes) -> tuple[int, ...]:
    """Counts of one text, in the order of FEATURES after doc_id. Bytes >= 0x80 that start a code point count as letters."""
    words = raw.split()
    hist = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    points = len(raw) - int(hist[0x80:0xC0].sum())
    repeated = 0
    if len(words) > 3:
        windows = list(zip(words, words[1:], words[2:], strict=False))
        if len(set(windows)) < len(windows):
            seen, covered = Counter(windows), -1
            for i, w in enumerate(windows):
                if seen[w] > 1:
                    repeated += i + 2 - max(covered, i - 1)
                    covered = i + 2
    lines, earlier, dup = 0, set(), 0
    for line in raw.split(b"\n"):
        if line.strip():
            lines += 1
            if line in earlier:
                dup += 1
            else:
                earlier.add(line)
    upper = int(hist[65:91].sum())
    letters = upper + int(hist[97:123].sum()) + int(hist[0xC0:].sum())
    return len(words), points - int(hist[_SPACES].sum()), int(hist[_SYMBOLS].sum()), dup, repeated, lines, letters, upper, int(hist[33])


def _counts(texts: list[bytes]) -> list[pa.Array]:
    return [pa.array(c, pa.int64()) for c in zip(*map(measure, texts), strict=True)]


def _measured(batches):
    for rows, texts in slices(batches):
        yield pa.RecordBatch.from_arrays([column(rows, "doc_id").cast(pa.int64()), *_counts(texts)], schema=_ARROW)


def rules() -> dict[str, Column]:
    """Each rule as a vote of +1, -1 or 0; thresholds leave a band between where the rule abstains."""
    words, chars = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("word_chars"), F.lit(1))

    def vote(value: Column, good: Column, bad: Column) -> Column:
        return F.when(bad, -1).when(good, 1).otherwise(0)

    def low_is_good(value: Column, good: float, bad: float) -> Column:
        return vote(value, value <= good, value > bad)

    mean = chars / words
    return {
        "length": vote(words, words >= 80, words < 50),
        "word_length": vote(mean, mean.between(3, 11), (mean < 2) | (mean > 16)),
        "symbols": low_is_good(F.col("n_symbols") / words, 0.05, 0.3),
        "repeated_lines": low_is_good(F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)), 0.05, 0.3),
        "repeated_words": low_is_good(F.col("n_repeat_words") / words, 0.2, 0.5),
        "letters": low_is_good(1 - F.col("n_letters") / chars, 0.15, 0.4),
        "upper_case": low_is_good(F.col("n_upper") / F.greatest(F.col("n_letters"), F.lit(1)), 0.2, 0.6),
        "exclamation": low_is_good(F.col("n_bang") / words, 0.05, 0.3),
    }


def fit_votes(patterns: np.ndarray, counts: np.ndarray, rounds: int = 100) -> tuple[np.ndarray, np.ndarray, float]:
    """EM over vote vectors: rates[y, rule] = P(vote good | y, not abstaining), the posterior of good of each vector, the prior.

    y = 1 is good. Starts at accurate rules; smoothing keeps every rate inside (0, 1) and better than chance on its class,
    so classes cannot swap. No documents, or only abstentions, give the prior.
    """
    good, bad = (patterns > 0).astype(float), (patterns < 0).astype(float)
    weight = counts.astype(float)
    rates, prior = np.tile([[0.3], [0.9]], (1, patterns.shape[1])), 0.8
    post = np.full(len(patterns), prior)
    for _ in range(rounds):
        log = [np.log(p) + good @ np.log(r) + bad @ np.log1p(-r) for p, r in ((1 - prior, rates[0]), (prior, rates[1]))]
        before, post = post, 1 / (1 + np.exp(np.clip(log[0] - log[1], -700, 700)))
        for y, share in ((0, weight * (1 - post)), (1, weight * post)):
            hits, all_votes = share @ good, share @ (good + bad)
            rates[y] = (hits + (2 if y else 1)) / (all_votes + 3)
        rates[0] = np.clip(rates[0], 0.01, 0.75)
        rates[1] = np.clip(rates[1], 0.8, 0.999)
        prior = float(np.clip((weight @ post + 8) / (weight.sum() + 10), 0.05, 0.99))
        if len(post) and np.abs(post - before).max() < 1e-9:
            break
    return rates, post, prior


def score_quality(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = 0.5) -> DataFrame:
    """One row per input row: counts, ``base_failed``, ``quality`` (posterior of good) and ``kept``.

    Null and empty texts have no words and fail the base rule; repeated rows are scored alike; a null id stays null;
    an empty table gives an empty result.
    """
    counted = cut(documents(df, id_col, text_col).mapInArrow(_measured, FEATURES), "quality")
    return _judged(counted, _posteriors(counted), least)


def _votes() -> Column:
    return sum(((v + 1) * 3**i for i, v in enumerate(rules().values())), F.lit(0)).cast("int")


def _posteriors(counted: DataFrame) -> DataFrame:
    """votes, quality: the posterior of good for every vote vector that occurs."""
    found = counted.groupBy(_votes().alias("votes")).count().collect()  # at most 3**8 rows
    rules_held = len(rules())
    patterns = np.array([[r["votes"] // 3**i % 3 - 1 for i in range(rules_held)] for r in found]).reshape(len(found), rules_held)
    _, post, _ = fit_votes(patterns, np.array([r["count"] for r in found]))
    return counted.sparkSession.createDataFrame([(r["votes"], float(p)) for r, p in zip(found, post, strict=True)], "votes int, quality double")


def _judged(counted: DataFrame, scores: DataFrame, least: float) -> DataFrame:
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return counted.withColumn("votes", _votes()).join(F.broadcast(scores), "votes", "left").withColumn("base_failed", failed).withColumn("kept", ~failed & (F.col("quality") >= least))


def accepted(df: DataFrame, text_col: str = "text", least: float = 0.5) -> DataFrame:
    """The rows, with all their columns, whose text the rules accept. Every row is judged by its own text, so ids play no
    part: null and repeated ids are kept or rejected like others, equal texts alike. Null and empty texts go; an empty table
    stays empty. Texts are measured twice, once to count votes and once beside the row, and never shuffled."""
    scores = _posteriors(documents(df.select(F.lit(None).cast("long").alias("doc_id"), F.col(text_col).alias("text"))).mapInArrow(_measured, FEATURES))
    names = [f"in_{i}" for i in range(len(df.columns))]
    plain = df.toDF(*names)
    text = names[df.columns.index(text_col)]
    fields = StructType([*plain.schema.fields, *(StructField(x, LongType()) for x in _ARROW.names[1:])])

    def beside(batches):
        for rows, texts in slices(batches, text):
            yield pa.RecordBatch.from_arrays([*rows.columns, *_counts(texts)], names=[*names, *_ARROW.names[1:]])

    return _judged(plain.mapInArrow(beside, fields), scores, least).where("kept").select(*names).toDF(*df.columns)


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts and verdict of every document."""
    scored = score_quality(table(spark, sf_dir, "documents"))
    return scored.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality")
