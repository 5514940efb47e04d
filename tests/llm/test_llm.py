"""Operators against brute force on small fixtures with nulls, empties, repeats and clashing columns."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from shapegraph.llm import bpe, decontaminate, jaccard, langid, personal, quality, sharding, substrings, tokencount, urls
from shapegraph.llm.common import fresh_path
from shapegraph.llm.graph import components

LONG = "The quick brown fox jumps over the lazy dog while it reads about suffix arrays under a warm sun today. " * 3
DOCS = [(1, None), (2, ""), (3, LONG), (4, LONG), (4, LONG), (5, "x" + LONG[4:]), (6, LONG + " And one more line."), (7, "ab " * 400), (8, "été <|endoftext|> don't 日本 123"), (9, "a b"), (None, LONG), (10, "\n\n\n"), (11, "Mail a.b@c.example.com or +1 (523) 555-1055, 8.8.8.8")]
SCHEMA = "doc_id long, text string, d long, k string, n string, c string, h string"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*d, 0, "", "", "", "") for d in DOCS], SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_bpe_equals_library(docs, none):
    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    got = sorted((r["doc_id"] or 0, r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in bpe.encode(docs, path, lexicon_words=20).collect())
    want = []
    for i, t in DOCS:
        ids = library.encode(t or "", add_special_tokens=False).ids
        want.append((i or 0, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert got == sorted(want)
    assert bpe.encode(none, path).count() == 0


def test_frequent_words_take_whole_count_classes(spark, none):
    texts = ["a " * 9 + "b " * 9 + "c " * 3 + "d e f"] * 2
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    for most, want in ((1, []), (2, ["a", "b"]), (3, ["a", "b", "c"]), (5, ["a", "b", "c"]), (6, ["a", "b", "c", "d", "e", "f"])):
        assert sorted(w.decode() for w in bpe.frequent_words(df, most)) == want
    assert bpe.frequent_words(none, 5) == []


def test_transducer_numbers():
    words = {b"car": [1], b"cars": [2], b"cat": [3, 4], b"bars": [5]}
    t = bpe.Transducer.mapped(bpe.Transducer.compile(words))
    found = t.numbers([*words, b"ca", b"", b"carts"])
    assert [t.out[t.offsets[k] : t.offsets[k + 1]].tolist() for k in found[:4]] == list(words.values())
    assert found[4:].tolist() == [-1, -1, -1]


def test_token_cache(spark, docs, none):
    path, cache = public_tokenizers.path("byte_bpe_50k.json"), fresh_path(spark, "cache")
    library = Tokenizer.from_file(path)
    for _ in range(2):
        got = sorted((r["doc_id"] or 0, r["n_bytes"], r["n_tokens"]) for r in tokencount.cached_counts(docs, path, cache).collect())
        assert got == sorted((i or 0, len((t or "").encode()), len(library.encode(t or "", add_special_tokens=False).ids)) for i, t in DOCS)
        assert spark.read.parquet(cache).count() == len({t or "" for _, t in DOCS})
    assert tokencount.cached_counts(none, path, fresh_path(spark, "cache")).count() == 0


def brute_components(docs, width, percent):
    sets = []
    for i, t in docs:
        w = (t or "").encode().lower().split()
        sets.append((i, {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set()))
    group = list(range(len(sets)))
    for a in range(len(sets)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    least = {}
    for (i, _), g in zip(sets, group, strict=True):
        least[g] = min([x for x in (least.get(g), i) if x is not None], default=None)
    return sorted(((i or 0), len(s), least[g] or 0) for (i, s), g in zip(sets, group, strict=True))


@pytest.mark.parametrize("width,percent", [(3, 90), (5, 80)])
def test_jaccard(docs, width, percent):
    got = sorted((r["doc_id"] or 0, r["n_shingles"], r["component_id"] or 0) for r in jaccard.similar_groups(docs, width, percent).collect())
    assert got == brute_components(DOCS, width, percent)


def test_jaccard_in_chunks(spark, monkeypatch):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(300)]
    base = [rng.choice(words) for _ in range(120)]
    docs = []
    for i in range(40):
        w = list(base)
        for _ in range(rng.choice([0, 1, 2, 6])):
            w[rng.randrange(len(w))] = rng.choice(words)
        docs.append((i, " ".join(w)))
    monkeypatch.setattr(jaccard, "CHUNK", 4)
    monkeypatch.setattr(jaccard, "PIVOTS", 1)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert sorted(tuple(r) for r in jaccard.similar_groups(df, 3, 90).collect()) == brute_components(docs, 3, 90)


def test_jaccard_empty(none):
    assert jaccard.similar_groups(none).count() == 0


@pytest.mark.parametrize("hot", [1, substrings.HOT])
def test_substrings(docs, hot):
    seen, want = set(), {}
    for i, t in sorted({(i if i is not None else -1, t or "") for i, t in DOCS}):
        raw = t.encode()
        gone = bytearray(len(raw))
        for a in range(len(raw) - 99):
            if raw[a : a + 100] in seen:
                gone[a : a + 100] = b"\1" * 100
            seen.add(raw[a : a + 100])
        want[i] = (len(raw), sum(gone), hashlib.sha256(bytes(b for b, g in zip(raw, gone, strict=True) if not g)).hexdigest())
    got = substrings.repeated_substrings(docs, hot=hot).collect()
    assert len(got) == len(DOCS)
    for r in got:
        assert (r["n_bytes"], r["n_removed"], r["kept_sha256"]) == want[r["doc_id"] if r["doc_id"] is not None else -1]


def test_edit_pattern_is_sellers():
    rng = random.Random(1)
    for _ in range(300):
        p, t = ("".join(rng.choice("abc") for _ in range(rng.randint(1, n))) for n in (8, 20))
        row = [0] * (len(t) + 1)
        for i, c in enumerate(p, 1):
            new = [i]
            for j, d in enumerate(t, 1):
                new.append(min(row[j - 1] + (c != d), row[j] + 1, new[-1] + 1))
            row = new
        assert decontaminate.EditPattern(p).search(t) == (min(row), row.index(min(row)))


def test_contaminations(spark, docs, none):
    items = spark.createDataFrame([(1, "the quikc brown fox jumps over the lazzy dog while it reads"), (2, "nothing like this stands anywhere in those texts"), (3, None), (4, "")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminations(docs, items).collect()}
    assert got == {(i, 1) for i in (3, 4, 6, None)} | {(5, 1)} or got == {(i, 1) for i in (3, 4, 5, 6, None)}
    assert decontaminate.contaminations(none, items).count() == 0
    assert decontaminate.contaminations(docs, items.limit(0)).count() == 0


def test_personal(docs, none):
    rows = {r["doc_id"]: r for r in personal.personal_data(docs).collect()}
    assert (rows[11]["n_email"], rows[11]["n_ip"], rows[11]["n_phone"], rows[11]["n_card"]) == (1, 1, 1, 0)
    assert rows[11]["spans"] == "email:5:22,phone:26:43,ip:45:52"
    assert rows[3]["spans"] == "" and rows[1]["base_sha256"] == hashlib.sha256(b"").hexdigest()
    assert personal.redact("a x@y.com b", personal.base_spans("a x@y.com b")) == "a [EMAIL] b"
    assert personal.redacted(docs).columns == docs.columns and personal.personal_data(none).count() == 0
    held = [s for t in ['the token = "9f86d081884c7d659a2feaa0c55ad015a3bf4f1b" ends'] for s in personal.find_personal([t])[0][1]]
    assert [s[2] for s in held] == ["secret"]


def test_every_labelled_item_becomes_a_span():
    one, two = "9f86d081884c7d659a2feaa0c55ad015a3bf4f1b", "60303ae22b998861bce3b28f33eec1be758a213c"
    for gap in (" ", "\n"):
        text = f"{one}{gap}{two}"
        spans = personal.find_personal([text])[0][1]
        assert spans == [(0, 40, "secret"), (41, 81, "secret")] and personal.redact(text, spans) == f"[SECRET]{gap}[SECRET]"
    for mail in ("erla (at) onde (dot) com", "erla (AT) onde (DOT) com"):
        text = f"the {mail} an"
        assert personal.redact(text, personal.find_personal([text])[0][1]) == "the [EMAIL] an"
    # A base span parts a run; what it leaves of a secret is still one, and the mail beside it is not lost with it.
    text = f"{one} a.b@c.example.com erla (at) onde (dot) com"
    base = personal.base_spans(text)
    tokens = [m.span() for m in personal._TOKEN.finditer(text)][1:]
    assert personal.labelled_spans(text, "email", tokens, base) == [(text.index("erla"), len(text), "email")]
    glued = f"{one},a.b@c.example.com,{two}"
    assert [s[:2] for s in personal.labelled_spans(glued, "secret", [(0, len(glued))], personal.base_spans(glued))] == [(0, 40), (59, 99)]
    assert personal.labelled_spans("ab.cd-1 x", "secret", [(0, 7)], []) == [(0, 7, "secret")]


def test_gate_equals_ungated_decoding():
    rng = random.Random(3)
    parts = ["an", "the", "onde", "x" * 30, "At", "(AT)", "[at],", "Dot", "(dot)", "key", "Token:", "=", "call", "555-1055", "(523)", "9f86d081884c7d659a2feaa0c55ad015a3bf4f1b", "a@b", "1999", "com"]
    texts = [" ".join(rng.choice(parts[:4] if rng.random() < 0.6 else parts) for _ in range(rng.randint(0, 30))) for _ in range(400)]
    field, bases = personal.trained(), [personal.base_spans(t) for t in texts]
    whole = personal.field_spans(texts, field, bases, reach=None)
    assert personal.field_spans(texts, field, bases) == whole and sum(map(len, whole)) > 100
    assert personal.field_spans(["erla (AT) onde (DOT) com"], field, [[]]) == [[(0, 24, "email")]]


def test_viterbi_is_best_labelling():
    field = personal.trained()
    rng = np.random.default_rng(0)
    scores = rng.normal(size=(3, 3, len(personal.LABELS)))
    got = field.viterbi(scores)
    for run, labels in zip(scores, got, strict=True):
        def value(ls, run=run):
            path = [0, *ls, 0]
            return sum(field.step[a, b] for a, b in zip(path, path[1:], strict=False)) + sum(run[t, y] for t, y in enumerate(ls))

        n = len(personal.LABELS)
        best = max(((a, b, c) for a in range(n) for b in range(n) for c in range(n)), key=value)
        assert value(tuple(labels)) == pytest.approx(value(best))


def test_quality(docs, none):
    rows = {r["doc_id"]: r for r in quality.score_quality(docs).collect()}
    assert rows[7]["base_failed"] and not rows[7]["kept"] and rows[7]["n_repeat_words"] == 400
    assert rows[1]["n_words"] == 0 and rows[10]["n_dup_lines"] == 0
    assert quality.score_quality(none).count() == 0
    post = quality.fit_votes(np.array([[1, 1, 1], [-1, -1, -1], [1, 1, 0]]), np.array([80, 20, 5]))[1]
    assert post[0] > 0.9 and post[1] < 0.1 and post[2] > 0.8


def test_language():
    trees = langid.ContextTrees({"a": [b"abab" * 50], "b": [b"bcbc" * 50]})
    assert trees.bits([b"ababab", b"", b"bcbcbcz"]).argmin(axis=1).tolist() == [0, 0, 1]
    whole = trees.bits([b"abcab"])[0]
    # The frozen model's probabilities of the next byte sum to one over the symbols and the unseen.
    assert whole.min() > 0 and np.isfinite(whole).all()


def test_language_edge_cases(spark, docs, none):
    got = {r["doc_id"]: r for r in langid.identify(docs, langid.ContextTrees({"x": [LONG.encode()]})).collect()}
    assert got[1]["lang_pred"] == "und" and got[2]["lang_pred"] == "und" and got[3]["lang_pred"] == "x"
    assert langid.identify(docs, langid.ContextTrees({})).where("lang_pred <> 'und'").count() == 0


def test_urls(spark):
    pages = [(1, "http://www.a.com/x/1#t", '<link rel="canonical" href="http://b.org/y">'), (2, "http://b.org/y", None), (3, None, None), (4, "nothing", ""), (5, "https://c.net/z", '<meta http-equiv="refresh" content="0; url=http://good.com/ok">'), (6, "http://q.bad.io/p?x", "")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    rules = [("block", "a.com", "/x"), ("block", "c.net", "/"), ("allow", "good.com", "/ok"), ("block", "bad.io", "/p")]
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in urls.filter_urls(df, rules).collect()}
    assert got == {1: ("www.a.com", "/x/1", "a.com/x", "block"), 2: ("b.org", "/y", None, "block"), 3: ("", "", None, "allow"), 4: ("", "", None, "allow"), 5: ("c.net", "/z", "c.net/", "block"), 6: ("q.bad.io", "/p", "bad.io/p", "block")}
    assert urls.filter_urls(df.limit(0), rules).count() == 0


def test_query_rules_are_those_of_the_contract(spark, tmp_path):
    assert urls.QUERY_RULES == [("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/")]
    pages = [(1, "http://a.com/en/1", ""), (2, "http://q.example.com/en/7", ""), (3, "http://b.net/de/1", ""), (4, "http://example.net/de/8", ""), (5, "http://c.org/es/", ""), (6, "http://d.net/de/2", '<link rel="canonical" href="http://c.org/es/">')]
    spark.createDataFrame(pages, "page_id long, url string, html string").write.parquet(str(tmp_path / "pages.parquet"))
    got = {r["page_id"]: (r["rule"], r["verdict"]) for r in urls.op4_redirect_filter(spark, str(tmp_path)).collect()}
    assert got == {1: ("com/en/", "block"), 2: ("example.com/en/7", "allow"), 3: ("net/de/", "allow"), 4: ("example.net/de/8", "block"), 5: ("org/es/", "block"), 6: ("net/de/", "allow")}


def test_link_targets(spark):
    link = '<link rel="canonical" href="%s">'
    page = "http://a.org/d/e/f.html?q=1#t"
    want = {"https://b.org/y": "https://b.org/y", "//b.org/p": "http://b.org/p", "/p?x#y": "http://a.org/p?x#y", "g/h": "http://a.org/d/e/g/h", "../g": "http://a.org/d/g", "./": "http://a.org/d/e/", "/../a/./b/..": "http://a.org/a/", "?z=2": "http://a.org/d/e/f.html?z=2", "g?n=http://c.org/": "http://a.org/d/e/g?n=http://c.org/", "mailto:x@b.org": None, "#top": None}
    df = spark.createDataFrame([(t, page, link % t) for t in want] + [("bare", "http://a.org", link % "g"), ("timer", page, '<meta http-equiv="refresh" content="5">')], "t string, url string, html string")
    got = {r["t"]: r["found"] for r in df.select("t", urls.link_targets(df["html"], df["url"]).alias("found")).collect()}
    assert got == {t: [u] if u else [] for t, u in want.items()} | {"bare": ["http://a.org/g"], "timer": []}


def test_urls_that_are_only_linked_decide(spark):
    link = '<link rel="canonical" href="%s">'
    pages = [(1, "http://n1.org/a", link % "http://bad.io/p"), (2, "http://n2.org/a", link % "http://good.com/ok"), (3, "http://n2.org/b", link % "http://n2.org/a"), (4, "http://n4.org/a", link % "//bad.io/q"), (5, "http://n5.org/a", link % "https://www.b.org/y/"), (6, "http://b.org/y", ""), (7, "http://n7.org/a/b", link % "c"), (8, "http://n7.org/a/c", link % "http://bad.io/r"), (9, "http://n9.org/", ""), (10, "http://n10.org/", link % "http://bad.io/s"), (11, "http://n11.org/", link % "http://n10.org/"), (12, "http://n11.org/", '<meta http-equiv="refresh" content="0; url=http://good.com/ok2">')]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    got = {r["page_id"]: r for r in urls.filter_urls(df, [("block", "bad.io", "/"), ("allow", "good.com", "/ok")]).collect()}
    assert [i for i in sorted(got) if got[i]["verdict"] == "block"] == [1, 4, 7, 8]
    assert got[5]["root"] == got[6]["root"] and got[7]["root"] == got[8]["root"] and len(got) == len(pages)


def test_components(spark):
    n = 60
    edges = spark.createDataFrame([(f"{i:03}", f"{i + 1:03}") for i in range(n) if i != 30] + [("x", "x")], "a string, b string")
    got = dict(tuple(r) for r in components(edges, spark.createDataFrame([("x",)], "node string")).collect())
    assert {k: v for k, v in got.items() if k != "x"} == {f"{i:03}": "000" if i <= 30 else "031" for i in range(n + 1)} and got["x"] == "x"


def test_resharding(spark, docs, none):
    flow = sharding.min_cost_flow([5, 0, 7], [4, 4, 4], [[int(i != j) for j in range(3)] for i in range(3)])
    assert [sum(f) for f in flow] == [5, 0, 7] and [flow[i][i] for i in range(3)] == [4, 0, 4]
    many = spark.createDataFrame([(i, "x" * (i % 37)) for i in range(3000)], "doc_id long, text string")
    rows = sharding.reshard(many, 16).collect()
    sizes = [sum(r["size"] for r in rows if r["shard"] == k) for k in range(16)]
    assert len(rows) == 3000 and max(sizes) - min(sizes) <= 2 * 38
    for k in range(16):
        assert sorted(r["slot"] for r in rows if r["shard"] == k) == list(range(sum(r["shard"] == k for r in rows)))
    assert all(r["text_crc32"] == zlib.crc32(b"x" * (r["doc_id"] % 37)) for r in rows)
    assert sharding.reshard(docs, 16).count() == len(DOCS) and sharding.reshard(none, 16).count() == 0


def test_token_counts_add_up_over_words():
    """Counts of remembered words are the library's for the whole text, and a word is encoded once."""
    import random

    import public_tokenizers
    from tokenizers import Tokenizer

    from shapegraph.llm import tokencount

    path = public_tokenizers.path("byte_bpe_50k.json")
    counts = tokencount._encoder(path)
    rng = random.Random(7)
    bits = [" ", "  ", "\n", "a", "é", "Zz", "'s", "<|endoftext|>", "\x85", "　", "12", ".", "\x1c", "ω"]
    texts = ["", " ", "a  b", *("".join(rng.choice(bits) for _ in range(rng.randint(0, 25))) for _ in range(1000))]
    whole = Tokenizer.from_file(path)
    want = [len(x) for x in whole.encode_batch(texts, add_special_tokens=False)]
    assert counts(texts[:500]) + counts(texts[500:]) == want
    asked = []
    counts.whole = lambda ts, f=counts.whole: asked.extend(ts) or f(ts)
    assert counts(["seldom seldom word seldom", "first seldom"]) == counts(["seldom seldom word seldom", "first seldom"])
    assert asked.count(" seldom") == 1
