"""Language identification by prediction by partial matching.

Each language has a byte context tree of order 3 with escape probabilities (method C: a context that saw n bytes of q
kinds escapes with q / (n + q) to the next shorter one; below the empty context all 256 bytes are alike). An escape is
shared by all bytes, so the probabilities of the next byte sum to one. Statistics are frozen after training: a text's code
length is a sum over the windows of its lower-cased bytes. The trees are sparse, sorted tables of the windows that some
language has seen; what none has seen is an escape and a shorter window.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, documents, slices, table

#: Bound of the training sample: labelled documents for each language.
TRAIN_DOCS = 250
#: Bytes of its documents that a language learns from at most; a document that does not fit is left out whole.
TRAIN_BYTES = 4_000_000
#: Bytes of the frozen tables at most, since they are broadcast; beyond it the rarest longest windows are forgotten.
MODEL_BYTES = 256 << 20
ORDERS = 4

_LETTER = regex.compile(r"\p{L}")


def _codes(texts: list[bytes], order: int) -> np.ndarray:
    """All windows of ``order`` + 1 bytes as numbers; texts are parted by line ends."""
    raw = np.frombuffer(b"".join(b"\n\n\n" + t for t in texts), np.uint8).astype(np.uint32)
    code = np.zeros(max(0, len(raw) - order), np.uint32)
    for k in range(order + 1):
        code = code << np.uint32(8) | raw[k : len(raw) - order + k]
    return code


class ContextTrees:
    """Frozen trees of all languages. Of each order: sorted windows and their code lengths in bits (window, language), sorted
    contexts and the bits of their escape (context, language)."""

    def __init__(self, samples: dict[str, list[bytes]], most_bytes: int = MODEL_BYTES):
        self.langs = sorted(samples)
        seen = [[np.unique(_codes(samples[k], order), return_counts=True) for k in self.langs] for order in range(ORDERS)]
        self.windows: list[np.ndarray] = []
        self.least = [1] * ORDERS
        while True:
            self._freeze(seen)
            if self.nbytes <= most_bytes:
                return
            # Forget the rarest windows of the longest order that has any; the tree stays a tree and its sums one.
            order = max(o for o in range(ORDERS) if len(self.windows[o]))
            if order == 0:
                raise ValueError(f"{len(self.langs)} languages do not fit into {most_bytes} bytes")
            self.least[order] *= 2
            seen[order] = [(w[n >= self.least[order]], n[n >= self.least[order]]) for w, n in seen[order]]

    @property
    def nbytes(self) -> int:
        return sum(x.nbytes for part in (self.windows, self.cost, self.contexts, self.escape) for x in part)

    def _freeze(self, seen: list[list[tuple[np.ndarray, np.ndarray]]]) -> None:
        self.windows, self.cost, self.contexts, self.escape = [], [], [], []
        for order in range(ORDERS):
            windows = np.unique(np.concatenate([w for w, _ in seen[order]] or [np.zeros(0, np.uint32)]))
            contexts = np.unique(windows >> np.uint32(8)) if order else np.zeros(min(1, len(windows)), np.uint32)
            prob, escape = np.zeros((len(windows), len(self.langs))), np.ones((len(contexts), len(self.langs)))
            place = np.searchsorted(contexts, windows >> np.uint32(8)) if order else np.zeros(len(windows), np.int64)
            for k, (own, counts) in enumerate(seen[order]):
                if not len(own):
                    continue
                at = np.searchsorted(windows, own)
                total, kinds = np.bincount(place[at], counts, len(contexts)), np.bincount(place[at], minlength=len(contexts))
                met = total > 0
                escape[met, k] = kinds[met] / (total + kinds)[met]
                prob[at, k] = counts / (total + kinds)[place[at]]
            if len(windows):
                shorter = np.exp2(-self._bits(windows & np.uint32((1 << 8 * order) - 1) if order else windows, order - 1))
                prob += escape[place] * shorter
            self.windows.append(windows)
            self.contexts.append(contexts)
            self.cost.append(-np.log2(prob).astype(np.float32))
            self.escape.append(-np.log2(escape).astype(np.float32))

    def _bits(self, codes: np.ndarray, order: int) -> np.ndarray:
        """Code lengths (window, language) of windows of ``order`` + 1 bytes."""
        if order < 0 or not self.langs:
            return np.full((len(codes), len(self.langs)), 8.0, np.float32)
        windows, contexts = self.windows[order], self.contexts[order]
        out = np.zeros((len(codes), len(self.langs)), np.float32)
        at = np.minimum(np.searchsorted(windows, codes), max(0, len(windows) - 1))
        hit = windows[at] == codes if len(windows) else np.zeros(len(codes), bool)
        out[hit] = self.cost[order][at[hit]]
        rest = np.flatnonzero(~hit)
        if len(rest):
            missing = codes[rest]
            out[rest] = self._bits(missing & np.uint32((1 << 8 * order) - 1), order - 1)
            if len(contexts):
                context = missing >> np.uint32(8) if order else np.zeros(len(missing), np.uint32)
                at = np.minimum(np.searchsorted(contexts, context), len(contexts) - 1)
                known = contexts[at] == context
                out[rest[known]] += self.escape[order][at[known]]
        return out

    def bits(self, texts: list[bytes]) -> np.ndarray:
        """Code length of each text (rows) under each language (columns)."""
        out = np.zeros((len(texts), len(self.langs)))
        lengths = np.array([len(t) for t in texts], np.int64)
        full = np.flatnonzero(lengths)
        if not len(full) or not self.langs:
            return out
        codes = _codes([texts[i] for i in full], ORDERS - 1)
        different, back = np.unique(codes, return_inverse=True)
        costs = self._bits(different, ORDERS - 1)[back]
        # Sums over each text's own windows; the three that straddle two texts fall out.
        starts = np.concatenate([[0], np.cumsum(lengths[full] + 3)[:-1]])
        bounds = np.minimum(np.stack([starts, starts + lengths[full]], 1).ravel(), len(costs) - 1)
        sums = np.add.reduceat(costs, bounds, axis=0, dtype=np.float64)[::2]
        sums[-1] = costs[starts[-1] :].sum(axis=0, dtype=np.float64)
        out[full] = sums
        return out


def sample(df: DataFrame, id_col: str, text_col: str, lang_col: str, docs_each: int = TRAIN_DOCS, most_bytes: int = TRAIN_BYTES) -> dict[str, list[bytes]]:
    """Per language the texts of at most ``docs_each`` labelled documents, chosen by a hash of the id, of ``most_bytes`` bytes
    together. Hashes and lengths of about 1.5 times as many are looked at first; only chosen texts reach the driver."""
    rows = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang"))
    learn = rows.where("lang is not null and text is not null and crc32(cast(cast(doc_id as string) as binary)) % 5 != 0")
    held = {r["lang"]: r["count"] for r in learn.groupBy("lang").count().collect()}
    chance = F.lit(0.0)
    for lang, n in held.items():
        chance = F.when(F.col("lang") == lang, 1.5 * docs_each / n).otherwise(chance)
    rank = F.xxhash64(F.col("doc_id"))
    near = learn.where((F.pmod(rank, F.lit(1 << 30)) / float(1 << 30)) < chance).select("lang", "text", rank.alias("rank"), F.crc32(F.col("text").cast("binary")).alias("crc"))
    chosen: set[tuple[str, int, int]] = set()
    kept, used = dict.fromkeys(held, 0), dict.fromkeys(held, 0)
    for r in sorted(near.select("lang", "rank", "crc", F.octet_length("text").alias("size")).collect()):
        if kept[r["lang"]] < docs_each and used[r["lang"]] + r["size"] <= most_bytes:
            chosen.add((r["lang"], r["rank"], r["crc"]))
            kept[r["lang"]] += 1
            used[r["lang"]] += r["size"]
    if not chosen:
        return {}
    marked = F.broadcast(df.sparkSession.createDataFrame(sorted(chosen), "lang string, rank long, crc long"))
    out: dict[str, list[bytes]] = {}
    for r in sorted(near.join(marked, ["lang", "rank", "crc"], "left_semi").collect(), key=lambda r: (r["rank"], r["text"])):
        out.setdefault(r["lang"], []).append(r["text"].lower().encode())
    return out


def identify(df: DataFrame, trees: ContextTrees, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score (posterior of the language by code length, 0 to 1) and bits for every input row.

    ``und`` with score 0 for null texts, texts without a letter, or where nothing was learnt; ties go to the first name.
    Repeated rows give repeated rows, a null id stays null, an empty table gives an empty result.
    """
    shipped = df.sparkSession.sparkContext.broadcast(trees)  # at most MODEL_BYTES

    def run(batches):
        model = shipped.value
        for rows, texts in slices(batches, most=1 << 18):
            lowered = [t.decode("utf-8").lower() for t in texts]
            bits = model.bits([t.encode() for t in lowered])
            letters = [_LETTER.search(t) is not None and bool(model.langs) for t in lowered]
            lang, score, best = ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts))
            if model.langs:
                at = bits.argmin(axis=1)
                best = bits[np.arange(len(texts)), at]
                score = 1 / np.exp2(np.minimum(0, best[:, None] - bits)).sum(axis=1)
                lang = [model.langs[k] if ok else "und" for k, ok in zip(at, letters, strict=True)]
            yield pa.RecordBatch.from_arrays([column(rows, "doc_id"), pa.array(lang), pa.array(np.where(letters, score, 0.0)), pa.array(np.where(letters, best, 0.0))], names=["doc_id", "lang_pred", "score", "bits"])

    return documents(df, id_col, text_col).mapInArrow(run, "doc_id long, lang_pred string, score double, bits double")


def op3_language_ppm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The predicted language of all documents, learnt from labelled ones that are not held out."""
    docs = table(spark, sf_dir, "documents")
    found = identify(docs, ContextTrees(sample(docs, "doc_id", "text", "lang")))
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(0)) % 5 == 0
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score", "bits")
