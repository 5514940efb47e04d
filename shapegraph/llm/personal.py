"""Personal data: fixed patterns plus a linear-chain conditional random field.

The patterns give the base spans. The field labels white-space tokens from word-shape features; it is trained here, on
a small labelled table that a rule writes, and adds spans where no base span is: secrets, and forms of the four kinds
that the patterns miss. Tokens whose emission margin for "other" is more than the transitions can overturn are decided
alone; the runs between them go through Viterbi in numpy batches of equal length, which is the exact decoding.
"""

from __future__ import annotations

import functools
import hashlib
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import column, documents, slices, table

KINDS = ("email", "ip", "card", "phone", "secret")
LABELS = ("other", *KINDS)

_LOCAL = r"[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+"
#: An address at a given place, and one that starts where a run of its first characters starts: a run is read once.
EMAIL_HERE, EMAIL_RUN = re.compile(_LOCAL), re.compile(r"(?<![A-Za-z0-9._%+-])" + _LOCAL)
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile("[0-9]")
_TOKEN = re.compile(r"\S+")
_CUE = re.compile(r"[0-9@]")
#: What of a labelled run becomes a span: every match, so that no labelled item is left.
_SECRET = re.compile(r"[A-Za-z0-9+/=_-]{12,}")
_NUMBER = re.compile(r"[(+]?[0-9](?:[0-9 ().-]*[0-9])?")
_MAIL = re.compile(r"[^\W_](?:[\w.%+\[\]()@ -]*[^\W_])?")
_CORE = re.compile(r"[^\W_](?:.*[^\W_])?", re.S)

Span = tuple[int, int, str]


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost non-overlapping matches of the address pattern, in time linear in the text: a failing place inside a run
    says that the rest of the run fails too, and only the place after a match can lie inside one."""
    out, at = [], 0
    while m := (at and EMAIL_HERE.match(text, at)) or EMAIL_RUN.search(text, at):
        out.append(m.span())
        at = m.end()
    return out


def _octet(digits: str) -> bool:
    """At most 255, whatever the number of digits."""
    value = digits.lstrip("0")
    return len(value) < 3 or (len(value) == 3 and int(value) <= 255)


def base_spans(text: str) -> list[Span]:
    """(start, end, kind) of the patterns' matches that pass their test, by start and then in the order of KINDS."""
    out: list[Span] = []
    if "@" in text:
        out += [(*span, "email") for span in emails(text)]
    if _DIGIT.search(text):
        out += [(*m.span(), "ip") for m in IP.finditer(text) if all(map(_octet, m.group().split(".")))]
        for m in CARD.finditer(text):
            digits = m.group().replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append((*m.span(), "card"))
        if "+" in text:
            out += [(*m.span(), "phone") for m in PHONE.finditer(text) if 9 <= sum("0" <= c <= "9" for c in m.group()) <= 15]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


#: Words whose presence is a feature of the token and of its neighbours (fixed values).
CUES = {"token": "key", "key": "key", "secret": "key", "password": "key", "passwd": "key", "apikey": "key", "api_key": "key", "tel": "call", "phone": "call", "call": "call", "mobile": "call", "fax": "call", "mail": "mail", "email": "mail", "e-mail": "mail", "at": "at", "(at)": "at", "[at]": "at", "dot": "dot", "(dot)": "dot", "[dot]": "dot", "card": "card", "visa": "card", "ip": "host", "host": "host", "=": "eq", ":": "eq"}
_CLASS = str.maketrans({**{c: "d" for c in "0123456789"}, **{c: "x" for c in "abcdefghijklmnopqrstuvwxyz"}, **{c: "X" for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"}})
_RUN = re.compile(r"(.)\1+", re.S)


def cue_of(token: str) -> str:
    return CUES.get(token.lower().strip(".,;:!?") or token, "-")


def loud(token: str) -> bool:
    """Has a feature other than those of a plain word: a digit, an at sign or a cue."""
    return _CUE.search(token) is not None or cue_of(token) != "-"


def token_features(token: str) -> tuple[str, ...]:
    """Features of one token: its cue word, collapsed shape, length class, share of digits, and mixtures."""
    core = token.strip(".,;:!?\"'()[]{}<>#*&%$|")
    digits = sum("0" <= c <= "9" for c in core)
    found = [f"cue={cue_of(token)}"]
    if not digits and "@" not in core:
        return (*found, "plain", f"long={len(core) > 24}")
    shape = _RUN.sub(r"\1", core.translate(_CLASS))
    found += [f"shape={shape}" if len(shape) <= 8 else "shape=mixed", f"size={min(len(core) // 4, 6)}", f"digits={min(digits, 12) // 2}"]
    if "@" in core:
        found.append("at-sign")
    if len(core) >= 16 and digits and sum(c.isalpha() for c in core) >= 4 and re.fullmatch(r"[A-Za-z0-9+/=_-]+", core):
        found.append("dense")
    if core.count(".") == 3:
        found.append("three-dots")
    return tuple(found)


def labelled_table(seed: int = 7, rows: int = 240) -> list[tuple[list[str], list[str]]]:
    """The training sentences (tokens, labels), from a rule: filler words around one personal item or a harmless number."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice(["an", "er", "the", "ti", "on", "la", "de", "sch", "re"]) for _ in range(rng.randint(1, 4)))
    number = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    text = lambda alphabet, n: "".join(rng.choice(alphabet) for _ in range(n))
    makers = [
        lambda: ([rng.choice(["token", "key", "secret", "password", "api_key"]), rng.choice(["=", ":"]), f'"{text("0123456789abcdef", rng.choice([24, 32, 40]))}"'], ["other", "other", "secret"]),
        lambda: ([text("0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ", rng.choice([20, 28, 36]))], ["secret"]),
        lambda: ([rng.choice(["tel", "call", "phone"]), f"({number(3)})", f"{number(3)}-{number(4)}"], ["other", "phone", "phone"]),
        lambda: (["+1", f"({number(3)})", f"{number(3)}-{number(4)}"], ["phone", "phone", "phone"]),
        lambda: ([f"{number(3)}-{number(3)}-{number(4)}"], ["phone"]),
        lambda: ([word(), "(at)", word(), "(dot)", "com"], ["email"] * 5),
        lambda: ([f"{word()}.{number(2)}@mail.example.com"], ["email"]),
        lambda: ([".".join(number(2) for _ in range(4))], ["ip"]),
        lambda: ([number(4) for _ in range(4)], ["card"] * 4),
        # Harmless numbers and junk.
        lambda: ([rng.choice(["in", "of"]), str(rng.randint(1900, 2030))], ["other"] * 2),
        lambda: ([number(rng.randint(1, 3)), word()], ["other"] * 2),
        lambda: ([f"{number(1)}.{number(2)}"], ["other"]),
        lambda: ([f"{number(2)}%", f"{number(2)}:{number(2)}"], ["other"] * 2),
        lambda: ([f"{number(4)}-{number(2)}-{number(2)}"], ["other"]),
        lambda: ([f"v{number(1)}.{number(1)}.{number(1)}", f"{word()}{number(1)}"], ["other"] * 2),
        lambda: ([f"{word()}###", f"{word()}&&&", f"{word()}!!", "|"], ["other"] * 4),
        lambda: ([rng.choice(["token", "key", "card", "call", "phone", "mail", "at", "ip"]), word()], ["other"] * 2),
        lambda: ([number(rng.choice([5, 6, 8]))], ["other"]),
        lambda: (["x" * 30 + word()], ["other"]),
    ]
    out = []
    for i in range(rows):
        tokens, labels = makers[i % len(makers)]()
        before, after = [word() for _ in range(rng.randint(1, 4))], [word() for _ in range(rng.randint(1, 4))]
        out.append((before + tokens + after, ["other"] * len(before) + labels + ["other"] * len(after)))
    return out


class Field:
    """A linear-chain conditional random field; weights by gradient ascent on the penalised log-likelihood."""

    def __init__(self, data: list[tuple[list[str], list[str]]], rounds: int = 300, penalty: float = 0.02, rate: float = 0.15):
        names = sorted({f for tokens, _ in data for t in range(len(tokens)) for f in self.context(tokens, t)})
        self.index = {f: i for i, f in enumerate(names)}
        size = len(LABELS)
        self.emit, self.step = np.zeros((len(names), size)), np.zeros((size, size))
        longest = max(len(t) for t, _ in data)
        used = np.zeros((len(data), longest, len(names)))
        gold = np.zeros((len(data), longest, size))
        real = np.zeros((len(data), longest), bool)
        for i, (tokens, labels) in enumerate(data):
            for t, label in enumerate(labels):
                used[i, t, [self.index[f] for f in self.context(tokens, t)]] = 1
                gold[i, t, LABELS.index(label)] = 1
                real[i, t] = True
        flat = used.reshape(-1, len(names))
        moves = np.einsum("ita,itb->ab", gold[:, :-1], gold[:, 1:])
        squares = [np.zeros_like(self.emit), np.zeros_like(self.step)]
        for _ in range(rounds):
            node, pair = self._expected((flat @ self.emit).reshape(gold.shape), real)
            slopes = [flat.T @ (gold - node).reshape(-1, size) - penalty * self.emit, moves - pair - penalty * self.step]
            for w, g, q in zip((self.emit, self.step), slopes, squares, strict=True):
                q += g * g
                w += rate * g / np.sqrt(q + 1e-8)
        # No transition can gain more than this over staying in "other" on both sides.
        self.margin = 2 * float(self.step.max() - self.step.min())

    @staticmethod
    def context(tokens: list[str], t: int) -> list[str]:
        own = list(token_features(tokens[t]))
        own += [f"before:{f}" for f in (token_features(tokens[t - 1])[:2] if t else ("edge",))]
        own += [f"after:{f}" for f in (token_features(tokens[t + 1])[:2] if t + 1 < len(tokens) else ("edge",))]
        return own

    def _expected(self, scores: np.ndarray, real: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Expected labels and moves, by forward and backward sums in logarithms; padding at the end is left out."""
        n, longest, size = scores.shape
        ahead, back = np.zeros(scores.shape), np.zeros(scores.shape)
        ahead[:, 0] = scores[:, 0]
        for t in range(1, longest):
            ahead[:, t] = scores[:, t] + np.logaddexp.reduce(ahead[:, t - 1, :, None] + self.step, axis=1)
        for t in range(longest - 2, -1, -1):
            on = np.logaddexp.reduce(self.step[None] + (scores[:, t + 1] + back[:, t + 1])[:, None, :], axis=2)
            back[:, t] = np.where(real[:, t + 1, None], on, 0)
        last = real.sum(axis=1) - 1
        total = np.logaddexp.reduce(ahead[np.arange(n), last], axis=1)
        node = np.where(real[:, :, None], np.exp(np.minimum(ahead + back - total[:, None, None], 0)), 0)
        pair = np.zeros((size, size))
        for t in range(longest - 1):
            joint = ahead[:, t, :, None] + self.step + (scores[:, t + 1] + back[:, t + 1])[:, None, :] - total[:, None, None]
            pair += np.exp(np.minimum(joint, 0))[real[:, t + 1]].sum(axis=0)
        return node, pair

    def emissions(self, tokens: list[str], t: int) -> np.ndarray:
        at = [self.index[f] for f in self.context(tokens, t) if f in self.index]
        return self.emit[at].sum(axis=0)

    def viterbi(self, batch: np.ndarray) -> np.ndarray:
        """Best labels of runs of one length: scores (run, place, label) between two tokens labelled "other"."""
        score, back = batch[:, 0] + self.step[0], []
        for t in range(1, batch.shape[1]):
            options = score[:, :, None] + self.step[None]
            back.append(options.argmax(axis=1))
            score = options.max(axis=1) + batch[:, t]
        best = [(score + self.step[:, 0]).argmax(axis=1)]
        for b in reversed(back):
            best.append(b[np.arange(len(b)), best[-1]])
        return np.stack(best[::-1], axis=1)


@functools.lru_cache(1)
def trained() -> Field:
    return Field(labelled_table())


#: Tokens this near (in tokens) to a loud one are scored. With the trained weights no best labelling leaves "other" for
#: two plain words in a row that have plain neighbours, so 2 is enough; a field of other weights may need more.
REACH = 4


def labelled_spans(text: str, kind: str, spots: list[tuple[int, int]], base: list[Span]) -> list[Span]:
    """The spans of one run of tokens labelled ``kind``, outside the base spans.

    Secrets end with their token; the part of one that a base span leaves is still secret. Of the other kinds, a token
    that a base span touches is already found, and it parts the run.
    """
    near = [s for s in base if s[0] < spots[-1][1] and spots[0][0] < s[1]]
    parts: list[tuple[int, int]] = []
    if kind == "secret":
        for a, b in spots:
            for c, d, _ in near:
                if c < b and a < d:
                    parts.append((a, c))
                    a = max(a, d)
            parts.append((a, b))
    else:
        joined = False
        for a, b in spots:
            free = all(b <= c or d <= a for c, d, _ in near)
            if free and joined:
                parts[-1] = (parts[-1][0], b)
            elif free:
                parts.append((a, b))
            joined = free
    pattern = {"secret": _SECRET, "email": _MAIL}.get(kind, _NUMBER)
    out: list[Span] = []
    for a, b in parts:
        if a < b:
            found = list(pattern.finditer(text, a, b))
            if kind == "secret" and not found:
                found = list(_CORE.finditer(text, a, b))
            out += [(*m.span(), kind) for m in found]
    return out


def field_spans(texts: list[str], field: Field, bases: list[list[Span]], reach: int | None = REACH) -> list[list[Span]]:
    """Spans that the field labels outside the base spans, for each text; runs of all texts are decoded together by length.

    ``reach`` None scores every token.
    """
    runs: dict[int, list[tuple[int, list[tuple[int, int]], np.ndarray]]] = {}
    for d, text in enumerate(texts):
        tokens = text.split()
        if reach is None:
            near = set(range(len(tokens)))
        else:
            near = set()
            for t, token in enumerate(tokens):
                if loud(token):
                    near.update(range(max(0, t - reach), min(len(tokens), t + reach + 1)))
        if not near:
            continue
        spots = [m.span() for m in _TOKEN.finditer(text)]
        run: list[tuple[int, np.ndarray]] = []

        def close(run=run, d=d, spots=spots):
            if run:
                runs.setdefault(len(run), []).append((d, [spots[t] for t, _ in run], np.stack([e for _, e in run])))
                run.clear()

        for t in sorted(near):
            scores = field.emissions(tokens, t)
            forced = scores[0] - scores[1:].max() > field.margin
            if run and (run[-1][0] != t - 1 or forced):
                close()
            if not forced:
                run.append((t, scores))
        close()
    out: list[list[Span]] = [[] for _ in texts]
    for group in runs.values():
        labels = field.viterbi(np.stack([g[2] for g in group]))
        for (d, spots, _), row in zip(group, labels.tolist(), strict=True):
            start = 0
            for t in range(1, len(row) + 1):
                if t == len(row) or row[t] != row[start]:
                    if row[start]:
                        out[d] += labelled_spans(texts[d], LABELS[row[start]], spots[start:t], bases[d])
                    start = t
    return [sorted(spans) for spans in out]


def find_personal(texts: list[str], field: Field | None = None) -> list[tuple[list[Span], list[Span]]]:
    """(base spans, all spans) of each text; an added span overlaps no base span."""
    bases = [base_spans(text) for text in texts]
    added = field_spans(texts, field or trained(), bases)
    return [(base, sorted(base + new, key=lambda s: (s[0], KINDS.index(s[2])))) for base, new in zip(bases, added, strict=True)]


def shown(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def redact(text: str, spans: list[Span]) -> str:
    """The text with each span (overlaps merged under the first kind) replaced by its kind in brackets."""
    out, at = [], 0
    for a, b, kind in spans:
        if a >= at:
            out += [text[at:a], f"[{kind.upper()}]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def personal_data(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per input row: base counts of the four kinds, digest of the base spans, all spans.

    Null and empty texts have none (the digest is that of the empty string); repeated rows give repeated rows, a null id
    stays null, an empty table gives an empty result. Time is linear in a text's length, runs of one character included.
    """
    schema = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"
    field = df.sparkSession.sparkContext.broadcast(trained())

    def run(batches):
        for rows, texts in slices(batches):
            found = find_personal([t.decode("utf-8") for t in texts], field.value)
            counts = [pa.array([sum(s[2] == kind for s in base) for base, _ in found], pa.int64()) for kind in KINDS[:4]]
            digests = pa.array([hashlib.sha256(shown(base).encode()).hexdigest() for base, _ in found])
            yield pa.RecordBatch.from_arrays([column(rows, "doc_id"), *counts, digests, pa.array([shown(s) for _, s in found])], names=[p.split()[0] for p in schema.split(", ")])

    return documents(df, id_col, text_col).mapInArrow(run, schema)


def redacted(df: DataFrame, text_col: str = "text", chars_col: str | None = "n_chars") -> DataFrame:
    """The same rows and columns with personal data replaced; ``chars_col``, if there, is the new length. A null text stays
    null, repeated rows are changed alike, an empty table stays empty; other columns pass through, whatever their names."""
    field = df.sparkSession.sparkContext.broadcast(trained())
    place = df.columns.index(text_col)
    count = df.columns.index(chars_col) if chars_col in df.columns else None

    def run(batches):
        for rows, texts in slices(batches, text_col):
            values = [t.decode("utf-8") for t in texts]
            new = [redact(t, s) for t, (_, s) in zip(values, find_personal(values, field.value), strict=True)]
            valid = rows.column(place).is_valid().to_pylist()
            arrays = list(rows.columns)
            arrays[place] = pa.array([t if ok else None for t, ok in zip(new, valid, strict=True)], pa.string())
            if count is not None:
                kind = rows.column(count).type
                arrays[count] = pa.array([len(t) if ok else None for t, ok in zip(new, valid, strict=True)], kind)
            yield pa.RecordBatch.from_arrays(arrays, names=rows.schema.names)

    return df.mapInArrow(run, df.schema)


def op6_personal_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base counts, their digest and all spans of every document."""
    return personal_data(table(spark, sf_dir, "documents"))
