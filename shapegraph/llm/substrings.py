"""Exact removal of repeated byte strings by a hash-compared suffix sort.

Every window of WINDOW bytes holds an anchor: the place of its least 32-byte fingerprint (a prefix polynomial hash).
Equal windows have equal anchors at equal offsets, so only suffixes at anchors with the same fingerprint need sorting:

1. Anchors travel as (fingerprint, 96-bit hash of the surrounding context, document, place). A context seen before covers
   its whole surroundings at once: contexts are told apart by 160 bits (fingerprint and hash), not by their bytes. An
   anchor whose fingerprint has one context only is dropped.
2. The rest fetch their contexts. Within a fingerprint, the suffixes to the right of the anchors and the reversed
   prefixes to the left are mergesorted; a comparison finds the common extension by binary search over prefix hashes.
   Common lengths of neighbours are verified on the bytes. They give, for each of the 69 windows around an anchor, the
   first document and place that has it.
3. A fingerprint with more than HOT different contexts is not sorted in one task: its windows themselves, all 100 bytes,
   are the key of an aggregation that finds their first places, so nothing is cut off and the bytes decide.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import column, cut, documents, slices, table

WINDOW, GRAM = 100, 32
#: Places in a window where a fingerprint can start.
SPAN = WINDOW - GRAM + 1
#: Contexts that are sorted together; a fingerprint with more takes the way of whole windows.
SORT_ROWS = 20_000
HOT = SORT_ROWS

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_LETTERS = np.frombuffer(b"".join(hashlib.blake2b(bytes([i]), digest_size=8).digest() for i in range(256)), np.uint64)


def _powers(n: int, base: np.uint64) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_POWER, _UNPOWER = _powers(1 << 16, _BASE), _powers(1 << 16, _INVERSE)


def _long_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if n <= len(_POWER):
        return _POWER[:n], _UNPOWER[:n]
    return _powers(n, _BASE), _powers(n, _INVERSE)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


def _sliding(op, x: np.ndarray, width: int) -> np.ndarray:
    """op over x[i : i + width] for every i, by doubling."""
    done, out = 1, x
    while done * 2 <= width:
        out = op(out[:-done], out[done:])
        done *= 2
    return out if done == width else op(out[: len(out) - (width - done)], out[width - done :])


def anchors(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Places and fingerprints of all anchors of a text of at least WINDOW bytes."""
    raw = np.frombuffer(text, np.uint8)
    power, unpower = _long_powers(len(raw))
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_LETTERS[raw] * power, dtype=np.uint64)])
    grams = _mix((sums[GRAM:] - sums[:-GRAM]) * unpower[: len(raw) - GRAM + 1])
    least = _sliding(np.minimum, grams, SPAN)  # of the window that starts here
    padded = np.concatenate([np.zeros(SPAN - 1, np.uint64), least, np.zeros(SPAN - 1, np.uint64)])
    at = np.flatnonzero(_sliding(np.maximum, padded, SPAN) == grams)
    return at, grams[at]


ANCHORS = "k long, x long, y int, d long, q long"


def _anchor_rows(batches):
    """Anchors of all texts; within a batch only the first of each (fingerprint, context), the others as covered (x = y = 0)."""
    for rows, texts in slices(batches):
        ids, marks = column(rows, "d").to_pylist(), column(rows, "h").to_pylist()
        parts = []
        for d, h, text in zip(ids, marks, texts, strict=True):
            if len(text) < WINDOW:
                continue
            at, keys = anchors(text)
            digests = b"".join(xxhash.xxh3_128_digest(text[max(0, p - SPAN + 1) : p + WINDOW], min(p, SPAN)) for p in at.tolist())
            contexts = np.frombuffer(digests, np.uint64).reshape(-1, 2)
            parts.append((keys, np.maximum(contexts[:, 0], np.uint64(1)), contexts[:, 1] & np.uint64(0xFFFFFFFF), np.full(len(at), d), np.array([h], np.uint64) << np.uint64(32) | at.astype(np.uint64)))
        if not parts:
            continue
        k, x, y, d, q = (np.concatenate(p) for p in zip(*parts, strict=True))
        q = q.view(np.int64)
        order = np.lexsort((q, d, y, x, k))
        k, x, y, d, q = k[order], x[order], y[order], d[order], q[order]
        head = np.concatenate([[True], (k[1:] != k[:-1]) | (x[1:] != x[:-1]) | (y[1:] != y[:-1])])
        first = np.maximum.accumulate(np.where(head, np.arange(len(k)), 0))
        covered = (d != d[first]) | (q != q[first])
        x, y = np.where(covered, np.uint64(0), x), np.where(covered, np.uint64(0), y)
        k = np.where(covered, _mix(q.view(np.uint64) ^ d.view(np.uint64)), k)
        yield pa.RecordBatch.from_arrays([pa.array(k.view(np.int64)), pa.array(x.view(np.int64)), pa.array(y.astype(np.uint32).view(np.int32)), pa.array(d), pa.array(q)], names=["k", "x", "y", "d", "q"])


class SuffixSort:
    """Mergesort of byte rows (given lengths, within groups) with comparisons by common extension."""

    def __init__(self, rows: np.ndarray, lengths: np.ndarray, groups: np.ndarray):
        self.rows, self.lengths, self.groups = rows, lengths, groups
        n, width = rows.shape
        self.hashes = np.zeros((n, width + 1), np.uint64)
        np.cumsum(_LETTERS[rows] * _POWER[:width], axis=1, dtype=np.uint64, out=self.hashes[:, 1:])
        self.order = self._sorted()
        a, b = self.order[:-1], self.order[1:]
        found = np.where(groups[a] == groups[b], self.extension(a, b), -1)
        # Verification: the common length on the bytes themselves.
        most = np.minimum(lengths[a], lengths[b])
        unequal = (rows[a] != rows[b]) | (np.arange(width)[None, :] >= most[:, None])
        true = np.where(groups[a] == groups[b], np.where(unequal.any(axis=1), unequal.argmax(axis=1), width), -1)
        if (true != found).any():  # a hash collision: sort by the bytes
            self.order = np.lexsort((lengths, *rows.T[::-1], groups))
            a, b = self.order[:-1], self.order[1:]
            most = np.minimum(lengths[a], lengths[b])
            unequal = (rows[a] != rows[b]) | (np.arange(width)[None, :] >= most[:, None])
            true = np.where(groups[a] == groups[b], np.where(unequal.any(axis=1), unequal.argmax(axis=1), width), -1)
        self.common = true

    def extension(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Common prefix length of rows a and b, by binary search over their prefix hashes."""
        low, high = np.zeros(len(a), np.int64), np.minimum(self.lengths[a], self.lengths[b])
        for _ in range(int(self.rows.shape[1]).bit_length()):
            middle = (low + high + 1) >> 1
            same = self.hashes[a, middle] == self.hashes[b, middle]
            low, high = np.where(same, middle, low), np.where(same, high, middle - 1)
        return low

    def less(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether row a sorts before row b; a row sorts before its extensions, equal rows by index."""
        out = self.groups[a] < self.groups[b]
        same = np.flatnonzero(self.groups[a] == self.groups[b])
        a, b = a[same], b[same]
        common = self.extension(a, b)
        ended = (common == self.lengths[a]) | (common == self.lengths[b])
        at = np.minimum(common, self.rows.shape[1] - 1)
        tie = (self.lengths[a] < self.lengths[b]) | ((self.lengths[a] == self.lengths[b]) & (a < b))
        out[same] = np.where(ended, tie, self.rows[a, at] < self.rows[b, at])
        return out

    def _sorted(self) -> np.ndarray:
        n = len(self.lengths)
        order, place, width = np.arange(n), np.arange(n), 1
        while width < n:
            # Each element's rank in the partner run, for all runs of this width at once.
            run = place // width
            partner = np.minimum((run ^ 1) * width, n)
            low, high = partner.copy(), np.minimum(partner + width, n)
            while (live := np.flatnonzero(low < high)).size:
                middle = (low[live] + high[live]) >> 1
                before = self.less(order[middle], order[live])
                low[live] = np.where(before, middle + 1, low[live])
                high[live] = np.where(before, high[live], middle)
            target = (run & ~1) * width + (place - run * width) + (low - partner)
            merged = np.empty(n, np.int64)
            merged[target] = order
            order, width = merged, width * 2
        return order


def _classes(sort: SuffixSort, length: int) -> np.ndarray:
    """Of each row the number of its class of rows with ``length`` bytes in common."""
    out = np.empty(len(sort.order), np.int64)
    out[sort.order] = np.concatenate([[0], np.cumsum(sort.common < length)])
    return out


def covered_by_earlier(keys, d, q, left: list[bytes], right: list[bytes]) -> list[tuple[int, int, int]]:
    """(row, start, end) relative to the anchor: what windows around it that have an earlier place cover."""
    order = np.lexsort((q, d))
    groups = np.unique(keys[order], return_inverse=True)[1]
    d, q = d[order], q[order]
    rights, lefts = [right[i] for i in order], [left[i][::-1] for i in order]
    sorts = []
    for rows, width in ((lefts, SPAN - 1), (rights, WINDOW)):
        lengths = np.array([len(r) for r in rows])
        sorts.append(SuffixSort(np.frombuffer(b"".join(r.ljust(width, b"\0") for r in rows), np.uint8).reshape(len(rows), width), lengths, groups))
    n = len(d)
    nearest, furthest = np.full(n, SPAN), np.full(n, -1)
    for o in range(SPAN):
        valid = np.flatnonzero((sorts[0].lengths >= o) & (sorts[1].lengths >= WINDOW - o))
        if len(valid) < 2:
            continue
        pair = _classes(sorts[0], o)[valid] * (n + 1) + _classes(sorts[1], WINDOW - o)[valid]
        _, first, member = np.unique(pair, return_index=True, return_inverse=True)
        first = valid[first[member]]
        again = valid[(d[first] != d[valid]) | (q[first] != q[valid])]
        nearest[again] = np.minimum(nearest[again], o)
        furthest[again] = o
    return [(int(order[i]), -int(furthest[i]), WINDOW - int(nearest[i])) for i in np.flatnonzero(furthest >= 0)]


COVERS = "d long, h long, a long, b long"


def _sorted_covers(batches):
    """Covers of a partition that is sorted by fingerprint; a run of whole groups is sorted at once."""

    def work(held: pa.Table):
        keys, d, q = (held.column(c).to_numpy() for c in ("k", "d", "q"))
        found = covered_by_earlier(keys, d, q, held.column("l").to_pylist(), held.column("r").to_pylist())
        if found:
            i, a, b = (np.array(v) for v in zip(*found, strict=True))
            place = q[i] & 0xFFFFFFFF
            return pa.RecordBatch.from_arrays([pa.array(d[i]), pa.array((q[i].view(np.uint64) >> np.uint64(32)).view(np.int64)), pa.array(place + a), pa.array(place + b)], names=["d", "h", "a", "b"])

    held = None
    for batch in batches:
        part = pa.Table.from_batches([batch])
        held = part if held is None else pa.concat_tables([held, part])
        while held.num_rows > SORT_ROWS:
            keys = held.column("k").to_numpy()
            # The last whole group that ends within SORT_ROWS; a larger one waits for its end.
            ends = np.flatnonzero(keys[1:] != keys[:-1]) + 1
            within = ends[ends <= SORT_ROWS]
            end = int(within[-1]) if len(within) else int(ends[0]) if len(ends) else 0
            if not end:
                break
            out, held = work(held.slice(0, end)), held.slice(end)
            if out is not None:
                yield out
    if held is not None and held.num_rows and (out := work(held)) is not None:
        yield out


def _contexts(batches):
    for rows, texts in slices(batches):
        ids, marks, wanted = (column(rows, c).to_pylist() for c in ("d", "h", "wanted"))
        out = []
        for d, h, text, want in zip(ids, marks, texts, wanted, strict=True):
            for w in want:
                p = w["p"]
                out.append((w["k"], w["hot"], d, p, h, text[max(0, p - SPAN + 1) : p], text[p : p + WINDOW]))
        if out:
            k, hot, d, p, h, left, right = zip(*out, strict=True)
            q = (np.array(h, np.uint64) << np.uint64(32) | np.array(p, np.uint64)).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(k, pa.int64()), pa.array(hot), pa.array(d, pa.int64()), pa.array(q), pa.array(left, pa.binary()), pa.array(right, pa.binary())], names=["k", "hot", "d", "q", "l", "r"])


def _windows(batches):
    for batch in batches:
        for at in range(0, batch.num_rows, 1000):
            part = batch.slice(at, 1000)
            w, d, q = [], [], []
            for di, qi, left, right in zip(*(column(part, c).to_pylist() for c in ("d", "q", "l", "r")), strict=True):
                whole = left + right
                for start in range(min(len(left), len(whole) - WINDOW) + 1):
                    w.append(whole[start : start + WINDOW])
                    d.append(di)
                    q.append(qi - len(left) + start)
            yield pa.RecordBatch.from_arrays([pa.array(w, pa.binary()), pa.array(d, pa.int64()), pa.array(q, pa.int64())], names=["w", "d", "q"])


def merged(intervals: list[tuple[int, int]], size: int) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted((max(0, a), min(b, size)) for a, b in intervals):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _kept(batches):
    for rows, texts in slices(batches):
        covers = column(rows, "covers").to_pylist()
        removed, runs, digests = [], [], []
        for text, cover in zip(texts, covers, strict=True):
            spans = merged([(c["a"], c["b"]) for c in cover or ()], len(text))
            digest, at = hashlib.sha256(), 0
            for a, b in spans:
                digest.update(text[at:a])
                at = b
            digest.update(text[at:])
            removed.append(sum(b - a for a, b in spans))
            runs.append([{"start": a, "end": b} for a, b in spans])
            digests.append(digest.hexdigest())
        sizes = pa.array([len(t) for t in texts], pa.int64())
        spans_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        yield pa.RecordBatch.from_arrays([column(rows, "doc_id"), sizes, pa.array(removed, pa.int64()), pa.array([len(r) for r in runs], pa.int64()), pa.array(digests), pa.array(runs, spans_type)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "removed"])


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, removed array<struct<start: long, end: long>>"


def repeated_substrings(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """Per input row: bytes, removed bytes, removed runs (their bounds in ``removed``), digest of what is left.

    A byte goes if a string of WINDOW bytes over it starts earlier too, in the order (doc_id, start), null ids first.
    Null and empty texts have 0 bytes. Rows with the same id and text count as one document and do not remove each
    other; rows with the same id and other texts are ordered by their checksums. An empty table gives an empty result.
    """
    smallest = F.lit(-(1 << 63)).cast("long")
    docs = documents(df, id_col, text_col).select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    docs = docs.select("doc_id", F.coalesce("doc_id", smallest).alias("d"), F.crc32(F.col("text").cast("binary")).alias("h"), "text")
    found = docs.select("d", "h", "text").mapInArrow(_anchor_rows, ANCHORS)
    # First by context, so that a fingerprint that many rows share is spread over its contexts; then only one row of each
    # context is counted by its fingerprint, with a partial count before the shuffle.
    first = F.first(F.struct("d", "q")).over(W.partitionBy("k", "x", "y").orderBy("d", "q"))
    seen = found.withColumn("first", first).withColumn("again", (F.col("x") == 0) | (F.col("first.d") != F.col("d")) | (F.col("first.q") != F.col("q")))
    seen = cut(seen.select("k", "d", "q", "again"), "anchors")
    mark, spot = F.shiftrightunsigned("q", 32).alias("h"), F.col("q").bitwiseAND(F.lit(0xFFFFFFFF)).alias("p")
    held = seen.where("not again").groupBy("k").agg(F.count("*").alias("held")).where("held > 1")
    several = seen.where("not again").join(held, "k").select("k", "d", mark, spot, (F.col("held") > hot).alias("hot"))
    whole = seen.where("again").select("d", mark, spot).select("d", "h", (F.col("p") - (SPAN - 1)).alias("a"), (F.col("p") + WINDOW).alias("b"))
    wanted = several.groupBy("d", "h").agg(F.collect_list(F.struct("k", "p", "hot")).alias("wanted"))
    around = docs.select("d", "h", "text").join(wanted, ["d", "h"]).mapInArrow(_contexts, "k long, hot boolean, d long, q long, l binary, r binary")
    around = cut(around, "contexts")
    cold = around.where("not hot").repartition("k").sortWithinPartitions("k").mapInArrow(_sorted_covers, COVERS)
    windows = cut(around.where("hot").mapInArrow(_windows, "w binary, d long, q long"), "windows")
    least = windows.groupBy("w").agg(F.min(F.struct("d", "q")).alias("first"))
    later = windows.join(least, "w").where((F.col("first.d") != F.col("d")) | (F.col("first.q") != F.col("q")))
    place = F.col("q").bitwiseAND(F.lit(0xFFFFFFFF))
    warm = later.select("d", F.shiftrightunsigned("q", 32).alias("h"), place.alias("a"), (place + WINDOW).alias("b"))
    covers = whole.unionByName(cold).unionByName(warm).groupBy("d", "h").agg(F.collect_list(F.struct("a", "b")).alias("covers"))
    return docs.join(covers, ["d", "h"], "left").select("doc_id", "text", "covers").mapInArrow(_kept, RESULT)


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes removed from every document, and the digest of what is left."""
    return repeated_substrings(table(spark, sf_dir, "documents")).drop("removed")
