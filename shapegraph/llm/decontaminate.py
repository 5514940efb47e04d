"""Benchmark decontamination by pigeonhole edit matching.

An item of n characters with an error budget of k is cut into k + 1 pieces: text within k edits of the item holds one
of them unchanged. All pieces of a block of items form one automaton; each exact hit proposes a place in the document,
and the bit-parallel distance of the item to the text around it decides.
"""

from __future__ import annotations

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, documents, slices, table

#: Characters of benchmark items that one broadcast automaton holds; more items make more blocks.
BLOCK_CHARS = 4_000_000
#: Allowed edits per character of an item.
ERROR_RATE = 0.08

MATCHES = "doc_id long, item_id long, distance int, start int, item_chars int"


def fold(text: str) -> str:
    """Lower case, white space runs as one blank."""
    return " ".join(text.lower().split())


def budget(chars: int, rate: float = ERROR_RATE) -> int:
    return int(chars * rate)


def cut_pieces(item: str, errors: int) -> list[tuple[int, str]]:
    """errors + 1 pieces of nearly equal length with their offsets."""
    bounds = [len(item) * i // (errors + 1) for i in range(errors + 2)]
    return [(a, item[a:b]) for a, b in zip(bounds, bounds[1:], strict=False) if b > a]


class EditPattern:
    """Bit-parallel edit distance of a pattern to its best substring of a text."""

    def __init__(self, pattern: str):
        self.size = len(pattern)
        self.places: dict[str, int] = {}
        for i, c in enumerate(pattern):
            self.places[c] = self.places.get(c, 0) | 1 << i

    def search(self, text: str) -> tuple[int, int]:
        """(least distance, end of the first substring that has it); starts are free."""
        ones, top = (1 << self.size) - 1, 1 << (self.size - 1)
        up, down, score = ones, 0, self.size  # vertical steps of +1 and -1
        best, end = score, 0
        for i, c in enumerate(text):
            match = self.places.get(c, 0)
            vertical = match | down
            across = (((match & up) + up) ^ up) | match
            rise = down | (ones & ~(across | up))
            fall = up & across
            score += bool(rise & top) - bool(fall & top)
            if score < best:
                best, end = score, i + 1
            rise, fall = rise << 1 & ones, fall << 1 & ones
            up = fall | (ones & ~(vertical | rise))
            down = rise & vertical
        return best, end


class ItemIndex:
    """The automaton of a block of items and the patterns that verify its hits."""

    def __init__(self, items: list[tuple[int, str]], rate: float):
        self.items = [(i, t, budget(len(t), rate)) for i, t in items if t]
        self.patterns: dict[int, EditPattern] = {}
        self.automaton = ahocorasick.Automaton()
        owners: dict[str, list[tuple[int, int]]] = {}
        for k, (_, item, errors) in enumerate(self.items):
            for offset, piece in cut_pieces(item, errors):
                owners.setdefault(piece, []).append((k, offset))
        for piece, owned in owners.items():
            self.automaton.add_word(piece, (len(piece), owned))
        if owners:
            self.automaton.make_automaton()

    def find(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item id, distance, start, item length) of the best match of each item within its budget."""
        if not self.items:
            return []
        tried: set[tuple[int, int]] = set()
        best: dict[int, tuple[int, int]] = {}
        for last, (size, owned) in self.automaton.iter(text):
            for k, offset in owned:
                _, item, errors = self.items[k]
                begin = last + 1 - size - offset
                key = (k, begin // (errors + 1))
                if key in tried or best.get(k, (1,))[0] == 0:
                    continue
                tried.add(key)
                low = max(0, (key[1] - 1) * (errors + 1))
                window = text[low : begin + len(item) + 2 * errors + 2]
                if k not in self.patterns:
                    self.patterns[k] = EditPattern(item)
                distance, end = self.patterns[k].search(window)
                if distance <= errors and distance < best.get(k, (errors + 1,))[0]:
                    best[k] = (distance, max(0, low + end - len(item)))
        return [(self.items[k][0], d, s, len(self.items[k][1])) for k, (d, s) in sorted(best.items())]


def _blocks(items: DataFrame, id_col: str, text_col: str):
    block, size = [], 0
    for r in documents(items, id_col, text_col).where("text is not null").toLocalIterator():
        text = fold(r["text"])
        block.append((r["doc_id"], text))
        size += len(text)
        if size >= BLOCK_CHARS:
            yield block
            block, size = [], 0
    if block:
        yield block


def contaminations(df: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", rate: float = ERROR_RATE) -> DataFrame:
    """One row for each document row and benchmark item that it holds within the item's budget: distance and place.

    Places and distances are in folded text (lower case, single blanks). Null and empty items match nothing, null and
    empty texts hold nothing; repeated rows give repeated matches; empty tables give an empty result. Items come in
    blocks of BLOCK_CHARS, each broadcast on its own; documents are scanned once for each block.
    """
    spark, docs, out = df.sparkSession, documents(df, id_col, text_col), None
    for block in _blocks(items, item_id_col, item_text_col):
        shipped = spark.sparkContext.broadcast(block)

        def scan(batches, shipped=shipped):
            index = ItemIndex(shipped.value, rate)
            for rows, texts in slices(batches):
                ids = column(rows, "doc_id").to_pylist()
                found = [(d, *m) for d, t in zip(ids, texts, strict=True) for m in index.find(fold(t.decode("utf-8")))]
                if found:
                    doc, item, distance, start, size = zip(*found, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(item, pa.int64()), pa.array(distance, pa.int32()), pa.array(start, pa.int32()), pa.array(size, pa.int32())], names=["doc_id", "item_id", "distance", "start", "item_chars"])

        part = docs.mapInArrow(scan, MATCHES)
        out = part if out is None else out.unionAll(part)
    return spark.createDataFrame([], MATCHES) if out is None else out


def without_items(df: DataFrame, items: DataFrame, text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", rate: float = ERROR_RATE) -> DataFrame:
    """The rows, with all their columns, whose text holds no item within its budget. Every row is judged by its own text:
    null and repeated ids play no part, null and empty texts stay, repeated rows share their fate, an empty table stays
    empty. Rows stream through one filter for each block of items; nothing is shuffled."""
    for block in _blocks(items, item_id_col, item_text_col):
        shipped = df.sparkSession.sparkContext.broadcast(block)

        def keep(batches, shipped=shipped):
            index = ItemIndex(shipped.value, rate)
            for rows, texts in slices(batches, text_col):
                clean = [not index.find(fold(t.decode("utf-8"))) for t in texts]
                yield rows if all(clean) else rows.filter(pa.array(clean))

        df = df.mapInArrow(keep, df.schema)
    return df


def op1_pigeonhole_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matches of all benchmark items in all documents."""
    return contaminations(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
