"""Measures on the worked graph of papers."""

import pytest

from shapegraph.measures import properties_of, redundant_triples, result_bytes, slice_curve
from shapegraph.plans.paths import Prop
from shapegraph.plans.patterns import why_not
from shapegraph.plans.shapes import AtMost, HasValue, all_of, some
from shapegraph.queries import Q, order_query
from shapegraph.sources.graph import TripleGraph

STUDENT = some("type", HasValue("<class/Student>"))
ROWS = [("<p>", "author", "<ann>"), ("<p>", "author", "<bob>"), ("<ann>", "type", "<class/Prof>"), ("<bob>", "type", "<class/Student>")]


@pytest.fixture(scope="module")
def paper(spark):
    return TripleGraph.from_rows(spark, ROWS)


def test_redundant_triples(paper):
    shape = all_of(some("author"), AtMost(1, Prop("author"), ~STUDENT))
    assert redundant_triples(paper, shape, "<p>") == [r for r in ROWS if r[1] == "author"]
    assert redundant_triples(paper, some("author", STUDENT), "<p>") == []
    with pytest.raises(ValueError):
        redundant_triples(paper, shape, "<p>", most=1)


def test_result_bytes(paper):
    found = result_bytes(paper.triples())
    assert found["rows"] == 4 and found["bytes"] > 0


def test_slice_curve_and_properties(paper):
    assert set(slice_curve({"all": paper, "types": paper.restrict(["type"])}, STUDENT)) == {"all", "types"}
    assert properties_of(all_of(some("author"), AtMost(1, Prop("type"), STUDENT))) == {"author", "type"}


def test_measures_read_the_given_tables(spark):
    data = "/root/testdata/sf0.001"
    for name, files in (("measure_applicability", {"lineitem"}), ("measure_requests", {"lineitem", "orders"}), ("measure_sql_size", {"lineitem", "orders", "documents"})):
        read = {f.rsplit("/", 1)[-1].removesuffix(".parquet") for f in Q[name](spark, data).inputFiles()}
        assert files <= read
    assert why_not(order_query([(1, 7), (2, 8)])) is None and why_not(order_query([(1, 7), (2, 7)])) == "cycle"
    sizes = {(r["shape"], r["form"]): r["triples"] for r in Q["measure_sql_size"](spark, data).collect()}
    assert len(sizes) == 10 and min(sizes.values()) > 0
