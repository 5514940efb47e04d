"""The engine against the definitions on random graphs, the sufficiency of evidence, and the size of plans."""

import random

import pytest

from reference_eval import Reference
from shapegraph.operators.evidence import Engine
from shapegraph.plans.paths import ID, Prop, parse_path
from shapegraph.plans.shapes import TOP, AtLeast, AtMost, Closed, Compare, Disj, Eq, ForAll, HasValue, UniqueLang, all_of, any_of, exactly, some
from shapegraph.plans.shapes import test as checked
from shapegraph.plans.sqlgen import closures, run_sql, sql_subgraph
from shapegraph.sources.graph import TripleGraph

SEQ, LOOP, MAYBE = parse_path("p/^q"), parse_path("(p/q)*"), parse_path("p?")
SHAPES = [
    all_of(some("p", some("q")), AtMost(1, Prop("q"), ~some("p"))),
    any_of(exactly(1, Prop("p")), ForAll(SEQ, some("p", HasValue("<n1>")))),
    all_of(some("p"), AtMost(0, SEQ, ForAll(Prop("p"), checked("iri") & AtMost(0, Prop("q"), TOP)))),
    AtLeast(2, LOOP, some("p", checked("iri"))),
    ForAll(MAYBE, any_of(some("q"), checked("literal"))),
    Eq(SEQ, "p"), ~Eq(SEQ, "p"), ~Disj(SEQ, "q") | Disj(ID, "p"), ~Eq(ID, "p") & ~Disj(ID, "q"),
    all_of(some("r"), Compare(Prop("r"), "<=", "t")), ~Compare(Prop("r"), "<", "t"), ~UniqueLang(Prop("t")), all_of(UniqueLang(Prop("t")), ~Closed(frozenset({"p", "q"}))),
]


def random_triples(seed):
    rng = random.Random(seed)
    nodes, values = [f"<n{i}>" for i in range(6)], ['"1"^^integer', '"2.5"^^decimal', '"a"', '"b"', '"x"@en', '"y"@EN', '"z"@de']
    links = {(rng.choice(nodes), rng.choice("pq"), rng.choice(nodes)) for _ in range(16)}
    return links | {(rng.choice(nodes), rng.choice("rt"), rng.choice(values)) for _ in range(12)}


@pytest.mark.parametrize("k", range(len(SHAPES)))
def test_engine_equals_the_definitions(spark, k):
    shape, known = SHAPES[k], random_triples(k)
    ref = Reference(known)
    engine = Engine(TripleGraph.from_rows(spark, known))
    want = {v for v in ref.nodes if ref.holds(shape, v)}
    assert {r["v"] for r in engine.select_nodes(shape).collect()} == want
    shown = {t for v in want for t in ref.evidence(shape, v)}
    assert {tuple(r) for r in engine.subgraph(shape).collect()} == shown
    # What a node's evidence shows, any graph between it and the whole shows too.
    for v in want:
        own = Reference(ref.evidence(shape, v) | set(random.Random(k).sample(sorted(known), 5)))
        assert own.holds(shape, v) or v not in own.nodes


@pytest.mark.parametrize("k", [0, 6, 10, 11])
def test_translation_equals_the_definitions(spark, k):
    shape, known = SHAPES[k], random_triples(k)
    ref, g = Reference(known), TripleGraph.from_rows(spark, known)
    shown = {t for v in ref.nodes for t in ref.evidence(shape, v)}
    assert {tuple(r) for r in run_sql(g, sql_subgraph([shape], closure=closures(g))).collect()} == shown


def test_plans_grow_with_the_shape(spark):
    g = TripleGraph.from_rows(spark, [("<a>", f"p{i}", f"<b{i}>") for i in range(6)])
    sizes = []
    for n in range(1, 6):
        plan = Engine(g).select_nodes(all_of(*(exactly(1, Prop(f"p{i}")) for i in range(n))))._jdf.queryExecution().analyzed().treeString()
        sizes.append((plan.count("Join"), plan.count("LocalRelation")))
    assert all(j == 0 for j, _ in sizes) and [r for _, r in sizes] == [r + sizes[0][1] * i for i, r in enumerate([sizes[0][1]] * 5)]
