"""Operators and pipeline stages against brute force: nulls, repeated ids, long texts, ties, empty tables, clashing names."""

import random
import time
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from pyspark.sql import functions as F
from shapegraph.llm import decontaminate, jaccard, langid, personal, quality, sharding, urls

WORDS = ["river", "stone", "light", "garden", "winter", "paper", "music", "window", "market", "forest", "silver", "letter", "summer", "bridge", "candle", "mirror"]


def prose(seed, n=90):
    rng = random.Random(seed)
    return " ".join(rng.choice(WORDS) + rng.choice(["", "s", "ed", "ing", "er", "ly"]) + str(rng.randrange(40) or "") for _ in range(n)) + "."


A, B, C = prose(1), prose(2), prose(3)
A2 = A.replace(A.split()[40], "changed", 1)
ROWS = [(1, A), (5, A2), (5, B), (None, A), (None, C), (7, C), (7, C), (8, None), (8, ""), (9, "  \n "), (9, "  \n "), (None, None)]
COLUMNS = "doc_id long, text string, __key string, __gone string, root string, c string, kept boolean, votes int"


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame([(*r, str(i), "", "", "", None, i) for i, r in enumerate(ROWS)], COLUMNS)


def texts(df):
    return Counter((r["doc_id"], r["text"]) for r in df.collect())


def test_near_copies_tells_rows_apart_by_id_and_text(rows):
    got = jaccard.keep_one(rows)
    assert got.columns == rows.columns
    assert texts(got) == Counter([(1, A), (5, B), (7, C), (8, None), (8, ""), (9, "  \n "), (9, "  \n "), (None, None)])
    assert jaccard.keep_one(rows.limit(0)).count() == 0


def test_repeated_ids_do_not_multiply_classes(spark):
    made = [(1 if i % 2 else None, prose(i // 2, 60)) for i in range(60)]
    df = spark.createDataFrame(made, "doc_id long, text string")
    got = jaccard.similar_groups(df, 3, 90).collect()
    assert len(got) == 60 and all(r["component_id"] == 1 for r in got)


def test_benchmark_stage_judges_each_text(spark, rows):
    item = " ".join(B.split()[10:30])
    items = spark.createDataFrame([(1, item), (2, None), (3, "")], "item_id long, text string")
    got = decontaminate.without_items(rows, items)
    assert texts(got) == Counter(r for r in ROWS if r[1] != B) and got.columns == rows.columns
    assert texts(decontaminate.without_items(rows, items.limit(0))) == Counter(ROWS)
    assert decontaminate.without_items(rows.limit(0), items).count() == 0


def distance_table(item, text):
    """Least edit distance of the item to any part of the text."""
    row = [0] * (len(text) + 1)
    for i, c in enumerate(item, 1):
        new = [i]
        for j, d in enumerate(text, 1):
            new.append(min(row[j - 1] + (c != d), row[j] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_contaminations_equal_a_distance_table(spark):
    rng = random.Random(4)
    items = [(i, prose(100 + i, 8)) for i in range(6)]
    docs = []
    for i in range(40):
        text = list(prose(i, 12) + " " + rng.choice(items)[1] + " " + prose(i + 50, 12))
        for _ in range(rng.choice([0, 1, 3, 5, 9, 14])):
            k = rng.randrange(len(text))
            text[k : k + rng.randint(0, 1)] = rng.choice(["", "q", "zz"])
        docs.append((i, "".join(text)))
    found = decontaminate.contaminations(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    got = {(r["doc_id"], r["item_id"]): r["distance"] for r in found}
    want = {}
    for d, text in docs:
        for k, item in items:
            folded = decontaminate.fold(item)
            least = distance_table(folded, decontaminate.fold(text))
            if least <= int(decontaminate.ERROR_RATE * len(folded)):
                want[d, k] = least
    assert got == want and len(want) > 10


def test_rules_stage_equals_scores(spark, rows):
    df = spark.createDataFrame([(i, prose(i, 90) if i % 3 else "### $$ && " * 40) for i in range(60)], "doc_id long, text string")
    kept = {r["doc_id"] for r in quality.score_quality(df).where("kept").collect()}
    assert {r["doc_id"] for r in quality.accepted(df).collect()} == kept and 0 < len(kept) < 60
    got = quality.accepted(rows)
    assert got.columns == rows.columns and texts(got) == Counter(r for r in ROWS if r[1] and len(r[1].split()) >= 50)
    assert quality.accepted(rows.limit(0)).count() == 0


def plain_counts(text):
    words = text.encode().split()
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = {w for w, n in Counter(windows).items() if n > 1}
    repeated = {i + k for i, w in enumerate(windows) if w in often for k in range(3)}
    lines, dup = set(), 0
    for line in text.split("\n"):
        if line.encode().split():
            dup += line in lines
            lines.add(line)
    return len(words), sum(len(w.decode()) for w in words), sum(c in "#*$%&|<>" for c in text), dup, len(repeated)


def test_base_counts_equal_plain_ones(spark):
    rng = random.Random(6)
    made = [(i, "".join(rng.choice(["a", "b ", "é", "\n", "#", "日 ", " ", "\t", "|", "a b a b "]) for _ in range(rng.randint(0, 120)))) for i in range(300)]
    got = quality.score_quality(spark.createDataFrame(made, "doc_id long, text string")).collect()
    want = {i: plain_counts(t) for i, t in made}
    assert {r["doc_id"]: (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in got} == want


def slow_base_spans(text):
    """The four patterns as they are stated, by the regular expression engine alone."""
    import re

    out = [(*m.span(), "email") for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [(*m.span(), "ip") for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        digits = re.sub("[ -]", "", m.group())
        if 12 <= len(digits) <= 19 and personal.luhn(digits):
            out.append((*m.span(), "card"))
    out += [(*m.span(), "phone") for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 9 <= sum(c.isdigit() for c in m.group()) <= 15]
    return sorted(out, key=lambda s: (s[0], personal.KINDS.index(s[2])))


def test_base_spans_equal_the_patterns():
    rng = random.Random(8)
    for _ in range(4000):
        text = "".join(rng.choice(["a", "b", ".", "@", "_", "-", " ", "1", "25", "+", "%", "(", "é", "4111111111111111", "10.0.0.1", "a@b.c"]) for _ in range(rng.randint(0, 40)))
        assert personal.base_spans(text) == slow_base_spans(text), text


def test_long_runs_are_linear():
    million = 1_000_000
    started = time.perf_counter()
    for text in ("1" * million, "1" * 5000 + ".1.1.1", "a" * million, "a" * million + "@b.c", "a@" * (million // 2), "1." * (million // 2), "+1(" * (million // 3), "x" * million + "@", "1 " * (million // 2)):
        personal.find_personal([text])
    assert time.perf_counter() - started < 120
    assert personal.base_spans("0" * 5000 + "1.2.3.4") == [(0, 5007, "ip")] and personal.base_spans("1" * 5000 + ".1.1.1") == []


def test_language_probabilities_sum_to_one():
    trees = langid.ContextTrees({"a": [b"abab cab" * 50, b"\xc3\xa9t\xc3\xa9"], "b": [b"bcbc" * 50], "c": [bytes(range(256))]})
    rng = random.Random(2)
    for _ in range(60):
        context = bytes(rng.choice([97, 98, 99, 32, 10, 195, 7, rng.randrange(256)]) for _ in range(3))
        codes = np.array([int.from_bytes(context + bytes([s]), "big") for s in range(256)], np.uint32)
        assert np.exp2(-trees._bits(codes, 3).astype(float)).sum(axis=0) == pytest.approx(np.ones(3), abs=1e-3)


def slow_bits(sample, text):
    """Code length by walking one language's contexts, as the method states it."""
    whole = b"".join(b"\n\n\n" + t for t in sample)
    seen = {}
    for order in range(4):
        for i in range(len(whole) - order):
            seen.setdefault(whole[i : i + order], Counter())[whole[i + order]] += 1

    def chance(context, byte):
        if context is None:
            return 1 / 256
        shorter = chance(context[1:] if context else None, byte)
        counts = seen.get(context)
        if not counts:
            return shorter
        total, kinds = sum(counts.values()), len(counts)
        return counts[byte] / (total + kinds) + kinds / (total + kinds) * shorter

    padded = b"\n\n\n" + text
    return -sum(np.log2(chance(padded[i - 3 : i], padded[i])) for i in range(3, len(padded)))


def test_code_lengths_equal_brute_force():
    samples = {"x": [b"the river and the stone", b"the light"], "y": [b"der fluss und der stein", b"das licht"]}
    trees = langid.ContextTrees(samples)
    held = [b"the stein", b"", b"zzz\xff", b"der light and", b"t"]
    want = [[slow_bits(samples[k], t) for k in ("x", "y")] for t in held]
    assert np.allclose(trees.bits(held), want, rtol=1e-4, atol=1e-3)


def test_language_model_is_bounded_and_held_out_accuracy(spark):
    rng = random.Random(9)
    made = {k: [" ".join(rng.choice(v) for _ in range(30)).encode() for _ in range(40)] for k, v in {"x": ["the", "and", "river", "stone"], "y": ["der", "und", "fluss", "stein"]}.items()}
    small = langid.ContextTrees(made, most_bytes=3_000)
    assert small.nbytes <= 3_000 and max(small.least) > 1
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    trees = langid.ContextTrees(langid.sample(docs, "doc_id", "text", "lang"))
    got = langid.identify(docs, trees).alias("p").join(docs, "doc_id").where("crc32(cast(cast(doc_id as string) as binary)) % 5 = 0 and lang is not null and lang_pred <> 'und'")
    held = got.selectExpr("count(*) as n", "avg(cast(lang_pred = lang as int)) as hit").first()
    assert held["n"] > 100 and held["hit"] >= 0.95


def test_flow_moves_the_fewest_bytes():
    rng = random.Random(11)
    for _ in range(200):
        n, m = rng.randint(1, 4), rng.randint(1, 5)
        supply = [rng.randint(0, 9) for _ in range(n)]
        capacity = sharding.even_capacities(sum(supply), m)
        flow = sharding.min_cost_flow(supply, capacity, [[int(i != j) for j in range(m)] for i in range(n)])
        assert [sum(f) for f in flow] == supply and all(sum(f[j] for f in flow) <= capacity[j] for j in range(m))
        # With cost one for leaving a shard, no plan keeps more in shard i than the less of what it has and may hold.
        assert sum(supply) - sum(flow[i][i] for i in range(min(n, m))) == sum(supply) - sum(map(min, supply, capacity))


def test_rewrite_keeps_every_row(spark, tmp_path):
    made = [(None, "a" * 50), (None, "b" * 40), (7, "same"), (7, "same"), (7, "other"), *((i, "x" * (i % 23)) for i in range(100, 400))]
    df = spark.createDataFrame([(*r, i) for i, r in enumerate(made)], "doc_id long, text string, mark int").repartition(5)
    plan = sharding.reshard(df, 6, old_count=4)
    written = sharding.rewrite(df, plan, str(tmp_path / "shards"))
    got = spark.read.parquet(str(tmp_path / "shards"))
    want = plan.where(plan["shard"].isin(written)).groupBy("shard").count()
    assert dict(tuple(r) for r in got.groupBy("shard").count().collect()) == dict(tuple(r) for r in want.collect())
    marks = [r["mark"] for r in got.collect()]
    assert len(marks) == len(set(marks)) and set(got.columns) == {"doc_id", "text", "mark", "shard"}
    moved = {r["doc_id"] for r in plan.where("shard <> old_shard").collect()}
    assert moved <= {r["doc_id"] for r in got.collect()}


def test_resharding_writes_the_shards_it_changes(spark, tmp_path):
    rng = random.Random(5)
    rows_ = [(rng.choice([None, *range(90)]), rng.choice([None, "", "é", "x" * rng.randrange(60)]), i) for i in range(400)]
    df = spark.createDataFrame(rows_, "doc_id long, text string, mark long")
    plan = sharding.reshard(df, 6, old_count=4)
    got = sharding.reshard(df, 6, old_count=4, out=str(tmp_path / "all"))
    assert Counter(tuple(r) for r in got.select(plan.columns).collect()) == Counter(tuple(r) for r in plan.collect())
    files = spark.read.parquet(str(tmp_path / "all"))
    assert Counter(tuple(r) for r in files.select("doc_id", "text", "mark").collect()) == Counter(rows_)
    for k in range(6):
        part = [r["slot"] for r in spark.read.parquet(str(tmp_path / f"all/shard={k}")).collect()]
        assert sorted(part) == list(range(len(part)))
    even = spark.createDataFrame([(i, "x" * 9) for i in range(40)], "doc_id long, text string")
    kept = sharding.reshard(even, 4, old_shard=even["doc_id"] % 4, old_count=4, out=str(tmp_path / "none"))
    assert kept.count() == 40 and not (tmp_path / "none").exists()
    one = sharding.reshard(even, 4, old_shard=F.when(even["doc_id"] < 20, 3).otherwise(even["doc_id"] % 2), old_count=4, out=str(tmp_path / "some"))
    assert sorted(p.name for p in (tmp_path / "some").glob("shard=*")) == ["shard=2", "shard=3"] and one.count() == 40
    query = sharding.op10_flow_resharding(spark, "/root/testdata/sf0.001")
    assert any("shards-" in f for f in query.inputFiles())


def slow_verdicts(pages, rules):
    """Rules by hand, then blocks through implied redirects and canonical links until nothing changes."""
    def split(u):
        if not u or "://" not in u:
            return "", ""
        rest = u.split("://", 1)[1]
        cut = min([rest.find(c) for c in "/?#" if c in rest] or [len(rest)])
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:cut])
        path = rest[cut:] if rest[cut:].startswith("/") else ""
        return host, path.split("?")[0].split("#")[0]

    out = {}
    for i, u, _ in pages:
        host, path = split(u)
        fits = [(len(h + p), v, h + p) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=None, key=lambda f: (f[0], f[1] != "block"))
        out[i] = (host, path, best[2] if best else None, best[1] if best else None)
    return out


def test_url_rules_equal_brute_force_and_ties_are_decided(spark):
    rng = random.Random(13)
    hosts, paths = ["a.com", "X.A.com", "b.net", "q.b.net", "notb.net", ""], ["", "/", "/en/", "/en/7", "/EN/7?x=1", "/de/8#f", "?q"]
    pages = [(i, rng.choice(["http://", "https://", ""]) + rng.choice(hosts) + rng.choice(paths), "") for i in range(200)] + [(200, None, None), (200, "", "")]
    rules = [("block", "a.com", "/en/"), ("allow", "x.a.com", "/en/7"), ("block", "net", "/"), ("allow", "b.net", "/de/"), ("allow", "q.b.net", "/"), ("block", "q.b.net", "/")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    got = urls.filter_urls(df, rules).collect()
    want = slow_verdicts(pages, rules)
    assert len(got) == len(pages)
    for r in got:
        host, path, rule, verdict = want[r["page_id"]]
        assert (r["host"], r["path"], r["rule"]) == (host, path, rule)
        assert verdict is None or r["verdict"] == verdict


def test_stages_run_on_each_other_and_on_nothing(spark, tmp_path):
    rng = random.Random(3)
    kinds = [prose(i % 40, 90) + (" mail a.b@c.example.com now" if i % 5 == 0 else "") for i in range(60)] + ["### $$ " * 60] * 5 + [None, ""]
    docs = spark.createDataFrame([(rng.randrange(50) if i % 7 else None, t, "en", "s", len(t or "")) for i, t in enumerate(kinds)], "doc_id long, text string, lang string, source string, n_chars long")
    spark.createDataFrame([(1, " ".join(prose(4, 90).split()[5:40]))], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    for table in (docs, docs.limit(0)):
        held = table
        for name, stage in corpus_pipeline.STAGES:
            columns = held.columns
            held = corpus_pipeline.cut(stage(spark, held, str(tmp_path)), name)
            assert name == "bpe_tokens" or held.columns == columns
    table = docs
    for _, stage in corpus_pipeline.STAGES[:4]:
        table = corpus_pipeline.cut(stage(spark, table, str(tmp_path)), "stage")
    left = [r["text"] for r in table.collect()]
    assert not any("@" in t for t in left) and all(prose(4, 90)[:60] not in t for t in left) and len(left) == len(set(left)) == 39
