"""BPE encoding and decoding over a minimal acyclic transducer.

Frequent words are counted over the whole corpus and compiled into a minimal acyclic automaton whose word numbers
(minimal perfect hash) index their ids. Executors memory-map the compiled file and walk it for a whole batch of words
at once; words outside it are merged exactly, pair by pair, also for a whole batch at once.
"""

from __future__ import annotations

import hashlib
import json
import mmap
import os
import struct
import tempfile
import unicodedata
from collections import Counter

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import column, cut, documents, slices, table

#: Words that the lexicon holds at most; with it the broadcast file stays below about 2 MB.
LEXICON_WORDS = 32_768
#: Distinct chunks that a task remembers at most before it starts anew.
MEMO_CHUNKS = 450_000

_ODD_SPACE = regex.compile(r"[\x1c-\x1f]")
_SPACE = regex.compile(r"[\t-\r \x85\xa0  -     　]+")
_PIECES = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")


#: Single marks that may end a word; each is a piece of its own.
_STOPS = frozenset(".,!?;:")


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, extra = [""] * 256, 0
    for b in range(256):
        if b in plain:
            out[b] = chr(b)
        else:
            out[b] = chr(256 + extra)
            extra += 1
    return out


class Vocabulary:
    """Symbols, merge ranks and special strings of a word-end BPE file (``</w>`` marks the end of a word)."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        model = data["model"]
        self.ids: dict[str, int] = model["vocab"]
        self.end = model["end_of_word_suffix"] or ""
        self.special = {t["content"]: t["id"] for t in data["added_tokens"]}
        self.tokens = {i: t for t, i in (self.ids | self.special).items()}
        letters = byte_letters()
        self.inner = np.array([self.ids.get(x, -1) for x in letters], np.int64)
        self.final = np.array([self.ids.get(x + self.end, -1) for x in letters], np.int64)
        keys, ranks, made = [], [], []
        for rank, merge in enumerate(model["merges"]):
            a, b = merge.split(" ") if isinstance(merge, str) else merge
            keys.append(self.ids[a] << 20 | self.ids[b])
            ranks.append(rank)
            made.append(self.ids[a + b])
        order = np.argsort(np.array(keys, np.int64), kind="stable")
        self.keys, self.ranks, self.made = (np.array(x, np.int64)[order] for x in (keys, ranks, made))
        self.split = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None

    def merge(self, words: list[bytes]) -> list[list[int]]:
        """Ids of each word by exact merging: again and again the pair of least rank, the leftmost of equals."""
        out: list[list[int]] = [[]] * len(words)
        by_length: dict[int, list[int]] = {}
        for i, w in enumerate(words):
            by_length.setdefault(len(w), []).append(i)
        none = np.int64(1 << 40)
        for length, at in by_length.items():
            if not length:
                continue
            for start in range(0, len(at), max(1, 200_000 // length)):
                part = at[start : start + max(1, 200_000 // length)]
                raw = np.frombuffer(b"".join(words[i] for i in part), np.uint8).reshape(len(part), length)
                symbols = self.inner[raw]
                symbols[:, -1] = self.final[raw[:, -1]]
                sizes = np.full(len(part), length)
                rank, made = self._pairs(symbols[:, :-1], symbols[:, 1:], none)
                live = np.arange(len(part))
                while length > 1 and len(live):
                    best = rank[live].argmin(axis=1)
                    good = rank[live, best] < none
                    live, best = live[good], best[good]
                    if not len(live):
                        break
                    symbols[live, best] = made[live, best]
                    # Close the gap: every column after the merged pair moves one to the left.
                    take = np.minimum(np.arange(length)[None, :] + (np.arange(length)[None, :] > best[:, None]), length - 1)
                    symbols[live] = np.take_along_axis(symbols[live], take, 1)
                    sizes[live] -= 1
                    take = np.minimum(np.arange(length - 1)[None, :] + (np.arange(length - 1)[None, :] > best[:, None]), length - 2)
                    rank[live], made[live] = np.take_along_axis(rank[live], take, 1), np.take_along_axis(made[live], take, 1)
                    for side in (best - 1, best):
                        ok = (side >= 0) & (side + 1 < sizes[live])
                        rows, cols = live[ok], side[ok]
                        rank[rows, cols], made[rows, cols] = self._pairs(symbols[rows, cols], symbols[rows, cols + 1], none)
                    rank[np.arange(length - 1)[None, :] >= (sizes - 1)[:, None]] = none
                for i, row, n in zip(part, symbols.tolist(), sizes.tolist(), strict=True):
                    out[i] = row[:n]
        return out

    def _pairs(self, left: np.ndarray, right: np.ndarray, none) -> tuple[np.ndarray, np.ndarray]:
        key = left << 20 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[at] == key
        return np.where(hit, self.ranks[at], none), self.made[at]


class Transducer:
    """A minimal acyclic automaton over bytes; each word's number selects its ids.

    Stored flat: for every edge its key (state * 256 + byte, ascending), its target and how many words sort before
    those that take the edge; per state whether it accepts; then offsets and ids.
    """

    @staticmethod
    def compile(words: dict[bytes, list[int]]) -> bytes:
        """Words in order, with suffixes shared as soon as they are complete."""
        ordered = sorted(words)
        register: dict[tuple, int] = {}
        states: list[tuple[bool, tuple[tuple[int, int], ...], int]] = []  # accepts, edges, words below

        def settle(node: list) -> int:
            key = (node[0], tuple(node[1]))
            if key not in register:
                register[key] = len(states)
                states.append((*key, node[0] + sum(states[t][2] for _, t in node[1])))
            return register[key]

        path: list[list] = [[False, []]]
        before = b""
        for w in ordered:
            shared = len(os.path.commonprefix([before, w]))
            while len(path) > shared + 1:
                done = path.pop()
                path[-1][1].append((before[len(path) - 1], settle(done)))
            path += [[False, []] for _ in w[shared:]]
            path[-1][0] = True
            before = w
        while len(path) > 1:
            done = path.pop()
            path[-1][1].append((before[len(path) - 1], settle(done)))
        root = settle(path[0])
        keys, targets, skipped = [], [], []
        for s, (accepts, edges, _) in enumerate(states):
            passed = int(accepts)
            for byte, t in edges:
                keys.append(s * 256 + byte)
                targets.append(t)
                skipped.append(passed)
                passed += states[t][2]
        offsets = np.cumsum([0] + [len(words[w]) for w in ordered])
        parts = [np.array(keys), np.array(targets), np.array(skipped), np.array([s[0] for s in states]), offsets, np.array([i for w in ordered for i in words[w]])]
        head = np.array([root] + [len(p) for p in parts], np.int32)
        return b"".join(p.astype(np.int32).tobytes() for p in (head, *parts))

    def __init__(self, data):
        ints = np.frombuffer(data, np.int32)
        self.root, at, parts = int(ints[0]), 7, []
        for n in ints[1:7]:
            parts.append(ints[at : at + n])
            at += n
        self.keys, self.targets, self.skipped, self.accepts, self.offsets, self.out = parts

    @classmethod
    def mapped(cls, data: bytes) -> Transducer:
        """From a file of the executor's temporary folder that is memory-mapped and at once unlinked."""
        with tempfile.TemporaryFile() as f:
            f.write(data)
            f.flush()
            return cls(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ))

    def numbers(self, words: list[bytes]) -> np.ndarray:
        """The number of each word, -1 for words that it does not hold; all words step together."""
        n = len(words)
        lengths = np.fromiter(map(len, words), np.int64, n)
        out, order = np.full(n, -1), np.argsort(-lengths, kind="stable")
        if not n or not len(self.keys):
            return out
        raw, starts = np.frombuffer(b"".join(words), np.uint8), np.cumsum(lengths) - lengths
        state, number, ok = np.full(n, self.root), np.zeros(n, np.int64), np.ones(n, bool)
        for step in range(int(lengths.max())):
            live = order[: np.searchsorted(-lengths[order], -step, "left")]  # longer than step
            live = live[ok[live]]
            if not len(live):
                break
            key = state[live] * 256 + raw[starts[live] + step]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            hit = self.keys[at] == key
            ok[live[~hit]] = False
            live, at = live[hit], at[hit]
            number[live] += self.skipped[at]
            state[live] = self.targets[at]
        ok &= self.accepts[state].astype(bool)
        out[ok] = number[ok]
        return out


def chunks(text: str) -> list[str]:
    """The text between runs of white space; pieces never reach across them."""
    if not _ODD_SPACE.search(text):  # then str.split() knows the same white space
        return text.split()
    return [c for c in _SPACE.split(text) if c]


def pieces(chunk: str) -> list[bytes]:
    """Normalised (composed, lower-case) words of a chunk."""
    if not chunk.isascii():
        chunk = unicodedata.normalize("NFC", chunk)
        chunk = chunk.lower() if "Σ" not in chunk else "".join(c.lower() for c in chunk)
    else:
        chunk = chunk.lower()
    if chunk.isalpha():
        return [chunk.encode()]
    if chunk[-1:] in _STOPS and chunk[:-1].isalpha():
        return [chunk[:-1].encode(), chunk[-1:].encode()]
    return [p.encode() for p in _PIECES.findall(chunk)]


class Codec:
    """Encodes and decodes whole texts; remembers the ids of chunks it has met, within MEMO_CHUNKS."""

    def __init__(self, vocabulary: Vocabulary, lexicon: Transducer):
        self.v, self.lexicon, self.memo, self.texts = vocabulary, lexicon, {}, {}
        self.shown = {i: t.encode() for i, t in vocabulary.tokens.items()}

    def learn(self, new: list[str]) -> None:
        split = [pieces(c) for c in new]
        words = list(dict.fromkeys(w for ps in split for w in ps))
        number = self.lexicon.numbers(words)
        ids: dict[bytes, list[int]] = {}
        offsets, out = self.lexicon.offsets, self.lexicon.out
        for w, k in zip(words, number.tolist(), strict=True):
            if k >= 0:
                ids[w] = out[offsets[k] : offsets[k + 1]].tolist()
        unseen = [w for w, k in zip(words, number.tolist(), strict=True) if k < 0]
        ids.update(zip(unseen, self.v.merge(unseen), strict=True))
        shown, memo, texts = self.shown, self.memo, self.texts
        for c, ps in zip(new, split, strict=True):
            all_ids = ids[ps[0]] if len(ps) == 1 else [i for p in ps for i in ids[p]]
            memo[c] = struct.pack(f"<{len(all_ids)}I", *all_ids)
            texts[c] = b" ".join([shown[i] for i in all_ids])

    def encode_batch(self, texts: list[str]) -> list[tuple[bytes, bytes]]:
        """For each text its ids as little-endian 32-bit integers, and its decoded text in UTF-8."""
        special = self.v.special
        split: list[list[str]] = []
        for t in texts:
            if special and any(s in t for s in special):
                parts = self.v.split.split(t)
                split.append([c for k, p in enumerate(parts) for c in ([p] if k % 2 else chunks(p))])
            else:
                split.append(chunks(t))
        if len(self.memo) > MEMO_CHUNKS:
            self.memo.clear()
            self.texts.clear()
        for s, i in special.items():
            self.memo[s], self.texts[s] = struct.pack("<I", i), s.encode()
        self.learn(list({c for cs in split for c in cs} - self.memo.keys()))
        ids, shown = self.memo.__getitem__, self.texts.__getitem__
        return [(b"".join(map(ids, cs)), b" ".join(map(shown, cs))) for cs in split]


def _word_counts(batches):
    for _, texts in slices(batches, most=8 << 20):
        seen: Counter[str] = Counter()
        for t in texts:
            seen.update(chunks(t.decode("utf-8")))
        words: Counter[bytes] = Counter()
        for c, n in seen.items():
            for p in pieces(c):
                words[p] += n
        yield pa.RecordBatch.from_arrays([pa.array(words.keys(), pa.binary()), pa.array(words.values(), pa.int64())], names=["word", "n"])


#: Steps that a doubling of a word's count is divided into when words are ranked; 64 doublings bound the histogram.
COUNT_STEPS = 16


def frequent_words(docs: DataFrame, most: int = LEXICON_WORDS) -> list[bytes]:
    """The words of the highest counts over all documents, by whole count classes that together hold ``most`` at most.

    Classes come first as a histogram of some hundred rows, so no more than ``most`` words ever reach the driver,
    from however many tasks; a class that does not fit whole is left to exact merging, and so are all below it.
    """
    rank = F.floor(F.log2("n") * COUNT_STEPS).cast("int")
    counts = docs.select("text").mapInArrow(_word_counts, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    counts = cut(counts.where(F.octet_length("word") <= 256).select("word", rank.alias("rank")), "word-counts")
    held, least = 0, None
    for row in counts.groupBy("rank").agg(F.count("*").alias("words")).orderBy(F.desc("rank")).collect():
        if held + row["words"] > most:
            break
        held, least = held + row["words"], row["rank"]
    if least is None:
        return []
    return [bytes(r["word"]) for r in counts.where(F.col("rank") >= least).select("word").collect()]


def encode(df: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", lexicon_words: int = LEXICON_WORDS, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids, decoded) for every input row, by whole texts.

    Null and empty texts have no ids and decode to the empty text; repeated rows give repeated rows.
    """
    docs = documents(df, id_col, text_col)
    vocabulary = Vocabulary(tokenizer)
    words = frequent_words(docs, lexicon_words)
    compiled = Transducer.compile(dict(zip(words, vocabulary.merge(words), strict=True)))
    shipped = df.sparkSession.sparkContext.broadcast(compiled)  # bounded by lexicon_words words of at most 256 bytes

    def run(batches):
        codec = Codec(Vocabulary(tokenizer), Transducer.mapped(shipped.value))
        for rows, texts in slices(batches, most=4 << 20):
            done = codec.encode_batch([t.decode("utf-8") for t in texts])
            arrays = [column(rows, "doc_id"), pa.array([len(i) // 4 for i, _ in done], pa.int64()), pa.array([hashlib.sha256(i).hexdigest() for i, _ in done]), pa.array([hashlib.sha256(d).hexdigest() for _, d in done])]
            if with_ids:
                arrays += [pa.array([np.frombuffer(i, "<u4").astype(np.int32) for i, _ in done], pa.list_(pa.int32())), pa.array([d.decode("utf-8") for _, d in done])]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_ids
    names = [part.split()[0] for part in schema.split(", ")]
    return docs.mapInArrow(run, schema)


def op2_bpe_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
