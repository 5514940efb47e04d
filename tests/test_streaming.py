"""Streams over several micro-batches."""

import pytest
from pyspark.sql import functions as F

from shapegraph.plans.shapes import HasValue, some
from shapegraph.queries import containment
from shapegraph.sources.graph import TRIPLES, fresh_path
from shapegraph.streaming.events import drain, keep_star, once_each, stream_table, window_counts


def written(spark, batches, schema, name):
    base = fresh_path(spark, "stream-test")
    for rows in batches:
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(f"{base}/{name}.parquet")
    return base


def test_star_judges_touched_subjects_anew(spark):
    shape = some("p", n=2) & ~some("q", HasValue('"bad"'))
    batches = [[("<a>", "p", "<1>"), ("<b>", "p", "<1>")], [("<a>", "p", "<2>"), ("<c>", "q", '"bad"')], [("<b>", "p", "<2>"), ("<b>", "q", '"bad"')]]
    base = written(spark, batches, TRIPLES, "triples")
    seen = keep_star(stream_table(spark, base, "triples", files_per_batch=1), shape, ["p", "q"])
    assert {(r["v"], r["ok"]) for r in seen.select("v", "ok").collect()} == {("<a>", True), ("<b>", False), ("<c>", False)}
    assert {(r["p"], r["o"]) for r in seen.where("ok and evidence").collect()} == {("p", "<1>"), ("p", "<2>")}


def test_repeats_across_batches_and_missing_times(spark):
    batches = [[(1, "2024-01-01 00:00:00"), (1, "2024-01-01 00:00:00"), (2, None)], [(1, "2024-01-01 00:10:00"), (3, "2024-01-01 00:20:00")]]
    base = written(spark, batches, "id long, ts string", "events")
    assert sorted(r["id"] for r in drain(once_each(stream_table(spark, base, "events", 1), "id"), "once").collect()) == [1, 3]
    hours = drain(window_counts(stream_table(spark, base, "events", 1), F.window("ts", "1 hour")), "hours", "complete")
    assert [r["n"] for r in hours.collect()] == [4]


@pytest.mark.parametrize("items", [[(1, "one two three four five"), (2, "o"), (3, ""), (4, None), (5, "b\nc  d e f")], []])
def test_containment_is_exact(spark, items):
    texts = [(1, "xone two three four fives"), (2, "one  two three four five"), (3, None), (4, ""), (5, "a b\nc  d e f"), (5, "a b\nc  d e f")]
    base = fresh_path(spark, "contains-test")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{base}/benchmark.parquet")
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{base}/documents.parquet")
    want = {(i, d) for i, a in items for d, b in texts if a is not None and b is not None and a in b}
    assert {tuple(r) for r in containment(spark, base).collect()} == want
