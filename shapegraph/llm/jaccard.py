"""Exact Jaccard join of word shingles with signature trees.

1. Documents with the same shingle set form one class; everything after works on one member of each class.
2. Every class posts the shingles of its prefix, in an order that puts heavy shingles last. Linked classes share a known
   number of them, so classes that meet others in fewer lists are done.
3. The classes of a posting list stand in a signature tree: nodes hold the OR of token bitmaps and a size range. A dual
   traversal prunes pairs of nodes by the greatest overlap that they allow, and pairs that are already connected; it
   leaves a forest, not all pairs. The forests' components are families that hold every link.
4. The classes of a family, now with their whole sets, go through the same traversal with exact verification.
A shingle is its 64-bit hash and a class is the 128-bit digest of its hashes; links are exact on those, not on the words.
Lists and families beyond CHUNK members are dealt out in chunks, each with a few common pivots; chunk pairs that the
first round has not connected are compared in a second one.
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
from .graph import components

#: Bits of the smallest bitmap; a set gets the power of two from 1.5 bits a member on, MOST_BITS at most.
LEAST_BITS, MOST_BITS = 256, 1 << 16
CHUNK, PIVOTS, LEAF = 2048, 8, 8
#: Shingles that the order of prefixes knows as heavy; any order gives the same links.
HEAVY = 65_536
#: Documents with candidates (40 bytes each) that are broadcast at most; beyond, they are shuffled.
BROADCAST_IDS = 200_000
#: A batch reports a shingle as heavy when this many of its documents hold it.
HEAVY_IN_BATCH = 8


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 150_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


_MULTIPLIERS = np.array([2 * int.from_bytes(hashlib.blake2b(bytes([i]), digest_size=8).digest(), "big") + 1 & (1 << 64) - 1 for i in range(32)], np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingle_sets(texts: list[bytes], width: int, memo: dict) -> list[np.ndarray]:
    """Sorted 64-bit hashes of each text's distinct shingles of ``width`` words (fewer words: the whole sequence)."""
    words = [t.lower().split() for t in texts]  # of bytes: A-Z and ASCII white space only
    flat = np.fromiter(map(memo.__getitem__, (w for ws in words for w in ws)), np.uint64)
    rolled = np.zeros(max(0, len(flat) - width + 1), np.uint64)
    for j in range(width):
        rolled += flat[j : len(flat) - width + 1 + j] * _MULTIPLIERS[j]
    rolled = _mix(rolled)
    out, at = [], 0
    for ws in words:
        n = len(ws)
        if n >= width:
            out.append(np.unique(rolled[at : at + n - width + 1]))
        elif n:
            out.append(_mix((flat[at : at + n] * _MULTIPLIERS[:n]).sum(dtype=np.uint64, keepdims=True) + np.uint64(n)))
        else:
            out.append(np.zeros(0, np.uint64))
        at += n
    return out


def digest(members: np.ndarray) -> bytes:
    return hashlib.blake2b(members.tobytes(), digest_size=16).digest()


def bitmap_size(n: int) -> int:
    return min(MOST_BITS, max(LEAST_BITS, 1 << int(1.5 * n).bit_length()))


def signature(members: np.ndarray, bits: int) -> np.ndarray:
    flags = np.zeros(bits, np.uint8)
    flags[(members >> np.uint64(7)) % np.uint64(bits)] = 1
    return np.packbits(flags, bitorder="little")


def folded(bits: np.ndarray, size: int) -> np.ndarray:
    """A bitmap's halves ORed until it has ``size`` bytes: the bitmap of the same set with fewer bits."""
    while len(bits) > size:
        bits = bits[: len(bits) // 2] | bits[len(bits) // 2 :]
    return bits


#: Percent of a set by which its prefix is longer than one shared element needs.
MORE = 3


def shared_at_least(n: int) -> int:
    """How many prefix elements linked sets share, if the smaller one has n elements."""
    return 1 + n * MORE // 100


def prefix_length(n: int, percent: int) -> int:
    """Of two linked sets, in any common order, the first so many elements have ``shared_at_least`` in common.

    Linked sets share a percent of the larger one at least; each prefix leaves out fewer than that less what must meet.
    """
    return n - -(-n * percent // 100) + shared_at_least(n) if n else 0


def linked(overlap, a, b, percent: int):
    return overlap * (100 + percent) >= percent * (a + b)


class SignatureTree:
    """Members by size; a binary hierarchy over them, as (low, high, left, right) with OR bitmaps and ranges."""

    def __init__(self, sizes: np.ndarray, bits: np.ndarray):
        self.order = np.argsort(sizes, kind="stable")
        self.sizes, self.bits = sizes[self.order].astype(np.int64), bits[self.order]
        self.ones = np.bitwise_count(self.bits).sum(axis=1).astype(np.int64)
        self.nodes: list[tuple] = []
        self.root = self._build(0, len(sizes))

    def _build(self, low: int, high: int) -> int:
        kids = ()
        if high - low > LEAF:
            middle = (low + high) // 2
            kids = (self._build(low, middle), self._build(middle, high))
            union = self.nodes[kids[0]][2] | self.nodes[kids[1]][2]
        else:
            union = np.bitwise_or.reduce(self.bits[low:high], axis=0)
        self.nodes.append((low, high, union, int(self.sizes[low]), int(self.sizes[high - 1]), int(self.ones[low:high].min()), kids))
        return len(self.nodes) - 1

    def forest(self, percent: int, verify=None, labels: np.ndarray | None = None) -> list[tuple[int, int]]:
        """Pairs of members that connect whatever linked pairs connect; ``labels`` tells what is connected before.

        A pair counts as linked if the greatest overlap that its bitmaps allow suffices and ``verify(i, j)``, if given,
        confirms it.
        """
        label = np.arange(len(self.sizes)) if labels is None else np.unique(labels[self.order], return_inverse=True)[1]
        out, stack = [], [(self.root, self.root)]
        while stack:
            p, q = stack.pop()
            low, high, union, least, most, ones, kids = self.nodes[p]
            low2, high2, union2, least2, most2, ones2, kids2 = self.nodes[q]
            if 100 * most < percent * least2 or 100 * most2 < percent * least:
                continue
            first = label[low]
            if (label[low:high] == first).all() and (label[low2:high2] == first).all():
                continue
            if p != q:
                common = int(np.bitwise_count(union & union2).sum())
                bound = min(most - max(0, ones - common), most2 - max(0, ones2 - common))
                if not linked(bound, least, least2, percent):
                    continue
            if kids or kids2:
                if p == q:
                    a, b = kids
                    stack += [(a, b), (b, b), (a, a)]
                elif kids and (not kids2 or high - low >= high2 - low2):
                    stack += [(k, q) for k in kids]
                else:
                    stack += [(p, k) for k in kids2]
                continue
            common = np.bitwise_count(self.bits[low:high, None, :] & self.bits[None, low2:high2, :]).sum(axis=2).astype(np.int64)
            a, b = self.sizes[low:high, None], self.sizes[None, low2:high2]
            bound = np.minimum(a - (self.ones[low:high, None] - common), b - (self.ones[None, low2:high2] - common))
            for i, j in zip(*np.nonzero(linked(bound, a, b, percent)), strict=True):
                i, j = int(i) + low, int(j) + low2
                if label[i] != label[j] and (verify is None or verify(int(self.order[i]), int(self.order[j]))):
                    label[label == label[j]] = label[i]
                    out.append((int(self.order[i]), int(self.order[j])))
        return out


def _groups(batches, keys: list[str]):
    """Runs of equal keys of a partition that is sorted by them, as one batch each."""
    held, current = [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = list(zip(*(column(batch, k).to_pylist() for k in keys), strict=True))
        start = 0
        for i in range(1, len(rows) + 1):
            if i == len(rows) or rows[i] != rows[start]:
                if held and rows[start] != current:
                    yield pa.Table.from_batches(held)
                    held = []
                current = rows[start]
                held.append(batch.slice(start, i - start))
                start = i
    if held:
        yield pa.Table.from_batches(held)


def _forest_of(group: pa.Table, percent: int) -> list[tuple[bytes, bytes]]:
    ids, sizes = group.column("c").to_pylist(), group.column("n").to_numpy()
    labels = np.unique(np.array([x or b for x, b in zip(group.column("label").to_pylist(), ids, strict=True)], object), return_inverse=True)[1] if "label" in group.column_names else None
    if "members" in group.column_names:
        sets = [np.frombuffer(m, np.uint64) for m in group.column("members").to_pylist()]
        width = bitmap_size(2 * int(sizes.max()))  # so that few unlinked pairs need verification
        bits = np.stack([signature(s, width) for s in sets]).view(np.uint64)

        def verify(i: int, j: int) -> bool:
            a, b = (sets[i], sets[j]) if len(sets[i]) <= len(sets[j]) else (sets[j], sets[i])
            at = np.minimum(np.searchsorted(b, a), len(b) - 1)
            return bool(linked(int((b[at] == a).sum()), len(a), len(b), percent))

        return [(ids[i], ids[j]) for i, j in SignatureTree(sizes, bits).forest(percent, verify, labels)]
    # Sets of compatible sizes have bitmaps of equal or neighbouring sizes; each such band has a tree of its own.
    maps = [np.frombuffer(s, np.uint8) for s in group.column("sig").to_pylist()]
    widths = np.array([len(m) for m in maps])
    out, done = [], set()
    for width in sorted(set(widths.tolist())):
        at = np.flatnonzero((widths == width) | (widths == 2 * width))
        if len(at) < 2 or (widths[at] == width).all() and width in done:
            continue
        done |= {width, 2 * width}
        bits = np.stack([folded(maps[i], width) for i in at]).view(np.uint64)
        found = SignatureTree(sizes[at], bits).forest(percent, None, None if labels is None else labels[at])
        out += [(ids[at[i]], ids[at[j]]) for i, j in found]
    return out


def _forests(rows: DataFrame, keys: list[str], percent: int) -> DataFrame:
    def run(batches):
        for group in _groups(batches, keys):
            if group.num_rows > 1:
                found = _forest_of(group, percent)
                if found:
                    a, b = zip(*found, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary())], names=["a", "b"])

    return rows.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(run, "a binary, b binary")


def linked_forest(rows: DataFrame, percent: int, tag: str, largest: int) -> DataFrame:
    """Edges (a, b) that connect, within each group ``g``, all classes ``c`` that linked pairs connect.

    rows: g, c, n and either ``sig`` or ``members``; ``largest`` is the size of the largest group.
    """
    if largest <= CHUNK:
        return _forests(rows, ["g"], percent)
    payload = [x for x in rows.columns if x not in ("g", "c", "n")]
    place = (F.row_number().over(W.partitionBy("g").orderBy("n", "c")) - 1).cast("long")
    numbered = cut(rows.withColumn("place", place).withColumn("chunk", (F.col("place") / CHUNK).cast("int")), tag)
    spread = numbered.where("chunk > 0").groupBy("g").agg(F.max("chunk").alias("last"))
    base = numbered.select("g", "chunk", "c", "n", *payload)
    pivots = numbered.where(F.col("place") < PIVOTS).join(spread, "g").withColumn("chunk", F.explode(F.sequence(F.lit(1), "last")))
    first = cut(_forests(base.unionByName(pivots.select(*base.columns)), ["g", "chunk"], percent), tag)
    labels = components(first, numbered.join(spread, "g", "left_semi").select(F.col("c").alias("node")).distinct())
    large = numbered.join(spread, "g", "left_semi").join(labels.select(F.col("node").alias("c"), F.col("root").alias("label")), "c", "left")
    # One row for each chunk of a large group.
    meta = large.groupBy("g", "chunk").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.min("n").alias("least"), F.max("n").alias("most"))
    other = meta.select("g", *(F.col(x).alias(f"{x}2") for x in ("chunk", "low", "high", "least", "most")))
    open_pairs = meta.join(other, "g").where("chunk < chunk2 and not (low = high and low2 = high2 and low = low2)").where((100 * F.col("most") >= percent * F.col("least2")) & (100 * F.col("most2") >= percent * F.col("least")))
    open_pairs = cut(open_pairs.select("g", "chunk", "chunk2"), tag)
    if open_pairs.isEmpty():
        return first
    sides = open_pairs.select("g", F.explode(F.array("chunk", "chunk2")).alias("side"), "chunk", "chunk2")
    second = sides.join(large.withColumnRenamed("chunk", "side"), ["g", "side"]).select("g", "chunk", "chunk2", "c", "n", "label", *payload)
    return first.unionByName(_forests(second, ["g", "chunk", "chunk2"], percent))


def similar_groups(df: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id for every input row; documents link at ``percent`` of Jaccard similarity or more.

    component_id is the smallest doc_id that links reach. Null texts and texts without words have no shingles and stay
    alone. Repeated rows are in one component; a null id is reached like any other and never the smallest unless all
    are null; an empty table gives an empty result.
    """
    described, of_class = _classes_of(documents(df, id_col, text_col), width, percent)
    alone = described.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return described.where("n > 0").select("doc_id", "n", "c").join(of_class, "c").select("doc_id", F.col("n").alias("n_shingles"), "component_id").unionByName(alone)


def _classes_of(docs: DataFrame, width: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """Rows doc_id, t (SHA-256 of the text), n, c (class) of all documents; and c, root, component_id of all classes with
    shingles. A class's representative is one (id, text), so a repeated id never brings in another text."""
    docs = docs.select("doc_id", F.unhex(F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256)).alias("t"), "text")

    def weigh(batches):
        memo = _WordHashes()
        for _, texts in slices(batches, most=4 << 20):
            sets = [s for at in range(0, len(texts), 256) for s in shingle_sets(texts[at : at + 256], width, memo)]
            values, counts = np.unique(np.concatenate(sets) if sets else np.zeros(0, np.uint64), return_counts=True)
            often = counts >= HEAVY_IN_BATCH
            yield pa.RecordBatch.from_arrays([pa.array(values[often].view(np.int64)), pa.array(counts[often])], names=["k", "n"])

    weights = docs.select("text").mapInArrow(weigh, "k long, n long").groupBy("k").agg(F.sum("n").alias("n"))
    heavy = weights.orderBy(F.desc("n"), "k").limit(HEAVY).collect()
    heavy_keys = np.array([r["k"] for r in heavy], np.int64).view(np.uint64)
    by_key = np.argsort(heavy_keys)
    shipped = docs.sparkSession.sparkContext.broadcast((heavy_keys[by_key], (len(heavy) - by_key).astype(np.uint64)))  # HEAVY entries at most

    def describe(batches):
        memo, (known, rank) = _WordHashes(), shipped.value
        for rows, texts in slices(batches):
            sets = shingle_sets(texts, width, memo)
            first = []
            for s in sets:
                want = prefix_length(len(s), percent)
                if len(known) and len(s):
                    at = np.minimum(np.searchsorted(known, s), len(known) - 1)
                    hit = known[at] == s
                    if hit.any():  # light shingles by hash, then heavy ones from the least heavy on
                        s = np.concatenate([s[~hit], s[hit][np.argsort(rank[at[hit]], kind="stable")]])
                first.append(s[:want].view(np.int64))
            arrays = [column(rows, "doc_id"), column(rows, "t"), pa.array([len(s) for s in sets], pa.int64()), pa.array([digest(s) for s in sets], pa.binary()), pa.array([signature(s, bitmap_size(len(s))).tobytes() for s in sets], pa.binary()), pa.array(first, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "t", "n", "c", "sig", "prefix"])

    described = cut(docs.mapInArrow(describe, "doc_id long, t binary, n long, c binary, sig binary, prefix array<long>"), "shingled")
    classes = cut(described.where("n > 0").groupBy("c").agg(F.min("doc_id").alias("least_id"), F.min(F.struct("doc_id", "t")).alias("rep"), F.first("n").alias("n"), F.first("sig").alias("sig"), F.first("prefix").alias("prefix")), "classes")
    posted = classes.select("c", "n", F.explode("prefix").alias("k"))
    same, by_size = W.partitionBy("k"), W.partitionBy("k").orderBy("n", "c")
    # Only members with a neighbour of compatible size can link within a list.
    near = (100 * F.lag("n").over(by_size) >= percent * F.col("n")) | (100 * F.col("n") >= percent * F.lead("n").over(by_size))
    posted = posted.withColumn("near", near).where("near").drop("near")
    posted = cut(posted, "postings")
    # A linked class meets its partner in as many lists as their prefixes share.
    smaller = F.ceil(F.col("n") * percent / 100)
    enough = posted.groupBy("c", "n").count().where(F.col("count") >= 1 + F.floor(smaller * MORE / 100)).select("c")
    posted = posted.join(enough, "c", "left_semi").withColumn("held", F.count("*").over(same)).where("held > 1")
    # A list is known by its length and three sums over its classes' digests (64, 64 and 32 bits): no weaker than the 128-bit
    # digests that tell classes apart, and no list is compared member by member.
    for i, mark in enumerate((F.xxhash64("c"), F.xxhash64("c", F.lit(1)))):
        posted = posted.withColumn(f"s{i}", F.sum(mark.cast("decimal(38,0)")).over(same))
    posted = cut(posted.withColumn("s2", F.sum(F.hash("c").cast("long")).over(same)), "postings")
    # Lists with the same classes need one traversal only.
    lists = posted.groupBy("held", "s0", "s1", "s2").agg(F.min("k").alias("k")).select("k")
    largest = posted.agg(F.max("held")).first()[0] or 0
    rows = posted.join(lists, "k", "left_semi").select(F.col("k").alias("g"), "c", "n").join(classes.select("c", "sig"), "c")
    maybe = cut(linked_forest(rows, percent, "lists", largest).distinct(), "maybe")
    families = cut(components(maybe, maybe.select(F.col("a").alias("node")).distinct()).select(F.col("node").alias("c"), F.col("root").alias("g")), "families")
    needed = cut(classes.join(families, "c").select("rep", "c", "g"), "needed")
    largest = families.groupBy("g").count().agg(F.max("count")).first()[0] or 0

    def members(batches):
        memo = _WordHashes()
        for rows, texts in slices(batches):
            sets = shingle_sets(texts, width, memo)
            yield pa.RecordBatch.from_arrays([column(rows, "g"), column(rows, "c"), pa.array([len(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["g", "c", "n", "members"])

    needed = needed.select(F.col("rep.doc_id").alias("rep_id"), F.col("rep.t").alias("rep_t"), "c", "g")
    few = F.broadcast(needed) if needed.count() <= BROADCAST_IDS else needed
    met = docs.join(few, (docs["t"] == F.col("rep_t")) & docs["doc_id"].eqNullSafe(F.col("rep_id"))).select("text", "c", "g")
    # Rows that repeat an id and its text bring their class once.
    held = met.mapInArrow(members, "g binary, c binary, n long, members binary").dropDuplicates(["c"])
    edges = cut(linked_forest(held, percent, "sets", largest), "edges")
    roots = components(edges, families.select(F.col("c").alias("node"))).select(F.col("node").alias("c"), "root")
    joined = classes.select("c", "least_id").join(roots, "c", "left").withColumn("root", F.coalesce("root", "c"))
    least = joined.groupBy("root").agg(F.min("least_id").alias("component_id"))
    return described.select("doc_id", "t", "n", "c"), cut(joined.join(least, "root").select("c", "root", "component_id"), "of-class")


def keep_one(df: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The input's rows and columns with one row of each group of near copies: that of the smallest id, null last, and among
    rows of one id that of the least text digest. Rows are told apart by id and text, so a row is never lost since another
    text has its id, and copies without an id go too. Texts without words are near copies of nothing and stay, repeated or
    not; an empty table stays empty. Other columns pass through; of rows that repeat both id and text any one stays."""
    described, of_class = _classes_of(documents(df, id_col, text_col), width, percent)
    member = described.where("n > 0").join(of_class.select("c", "root"), "c").select(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "t").alias("row"), "root")
    rows = cut(member.groupBy("root", "row").agg(F.count("*").alias("times")), "members")
    chosen = rows.groupBy("root").agg(F.min("row").alias("chosen"), F.count("*").alias("held"))
    judged = rows.join(chosen.where("held > 1"), "root", "left").withColumn("gone", F.coalesce(F.col("row") != F.col("chosen"), F.lit(False)))
    gone = cut(judged.where("gone or times > 1").select(F.col("row.doc_id").alias("gone_id"), F.col("row.t").alias("gone_text"), "gone"), "gone")
    names = [f"in_{i}" for i in range(len(df.columns))]  # names of one's own cannot clash with the input's
    own_id, own_text = (F.col(names[df.columns.index(x)]) for x in (id_col, text_col))
    keyed = df.toDF(*names).select("*", F.unhex(F.sha2(F.coalesce(own_text.cast("string"), F.lit("")).cast("binary"), 256)).alias("own_text"), own_id.cast("long").alias("own_id"))
    same = (F.col("own_text") == F.col("gone_text")) & F.col("own_id").eqNullSafe(F.col("gone_id"))
    shipped = F.broadcast(gone) if gone.count() <= BROADCAST_IDS else gone  # texts are shuffled beyond it only
    single = keyed.join(shipped, same, "left_anti").select(*names)
    repeated = gone.where("not gone")
    if repeated.isEmpty():
        return single.toDF(*df.columns)
    again = keyed.join(repeated, same, "left_semi").dropDuplicates(["own_id", "own_text"]).select(*names)
    return single.unionByName(again).toDF(*df.columns)


def op7_signature_tree_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Set sizes and components of all documents, linked at 0.9 on three-word shingles."""
    return similar_groups(table(spark, sf_dir, "documents"), 3, 90)
