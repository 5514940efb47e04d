"""Worked examples with known answers, rewriting laws, and the engines against each other."""

import os
import re

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from shapegraph.operators import evidence, reach
from shapegraph.operators.audit import audit_schema, audit_subgraph, audit_sufficiency
from shapegraph.operators.evidence import Engine, unimplied
from shapegraph.operators.reach import pairs, sources_of, trace_from, trace_sets
from shapegraph.operators.star import is_star, validate_and_extract_star
from shapegraph.plans.paths import ID, Inv, Prop, compile_path, parse_path, path, path_text
from shapegraph.plans import patterns, sqlgen
from shapegraph.plans.patterns import Edge, leaf, node, pattern_images, pattern_to_shape
from shapegraph.plans.shapes import BOTTOM, TOP, AtLeast, AtMost, Closed, Disj, Eq, ForAll, HasShape, HasValue, Not, ShapeDef, ShapeSchema, UniqueLang, all_of, class_target, conjuncts, exactly, less_than, negate, simplify, some, to_nnf
from shapegraph.plans.shapes import test as checked
from shapegraph.plans.sqlgen import closures, run_sql, sql_subgraph
from shapegraph.sources.graph import TripleGraph, cut, local
from shapegraph.sources.mapping import build_graph, kinds
from shapegraph.queries import Q, relevant
from shapegraph.workloads import SHAPES, hub, profile_shapes

PAPERS = [("<p1>", "type", "<class/Paper>"), ("<p2>", "type", "<class/Paper>"), ("<p1>", "author", "<ann>"), ("<p1>", "author", "<bob>"), ("<p2>", "author", "<ann>"), ("<ann>", "type", "<class/Prof>"), ("<bob>", "type", "<class/Student>"), ("<class/Student>", "subClassOf", "<class/Person>")]


def rows(df):
    return {tuple(r) for r in df.collect()}


@pytest.fixture(scope="module")
def papers(spark):
    return TripleGraph.from_rows(spark, PAPERS, frozenset({"subClassOf"}))


def nodes(df):
    return {r["v"] for r in df.collect()}


def test_student_author(papers):
    shape = some("author", class_target("Student"))
    schema = ShapeSchema([ShapeDef("Paper", shape, class_target("Paper"))])
    e = Engine(papers, schema)
    assert {r["focus"] for r in e.report().collect()} == {"<p2>"} and not e.conforms()
    assert rows(e.evidence_of(shape, "<p1>")) == {("<p1>", "author", "<bob>"), ("<bob>", "type", "<class/Student>")}
    assert rows(e.schema_subgraph()) == rows(e.evidence_of(shape, "<p1>")) | {("<p1>", "type", "<class/Paper>")}
    report, found = e.validate_and_extract()
    assert {r["focus"] for r in report.collect()} == {"<p2>"} and rows(found) == rows(e.schema_subgraph())


def test_at_most_keeps_what_shows_it(papers):
    shape = all_of(some("author"), AtMost(1, Prop("author"), ~some("type", HasValue("<class/Student>"))))
    assert rows(Engine(papers).evidence_of(shape, "<p1>")) == {("<p1>", "author", "<ann>"), ("<p1>", "author", "<bob>"), ("<bob>", "type", "<class/Student>")}


def test_antitone_shape_has_no_evidence(spark):
    g = TripleGraph.from_rows(spark, [("<a>", "p", "<b>")])
    e = Engine(g)
    assert nodes(e.conform(AtMost(0, Prop("p"), TOP), g.nodes())) == {"<b>"}
    assert rows(e.subgraph(AtMost(0, Prop("p"), TOP))) == set()


def test_loops(spark):
    g = TripleGraph.from_rows(spark, [("<a>", "p", "<a>"), ("<b>", "p", "<b>"), ("<b>", "p", "<c>")])
    e, v = Engine(g), g.nodes()
    assert nodes(e.conform(Not(Disj(ID, "p")), v)) == {"<a>", "<b>"} and nodes(e.conform(Eq(ID, "p"), v)) == {"<a>"}
    assert rows(e.evidence(Not(Disj(ID, "p")), v)) == {("<a>", "p", "<a>"), ("<b>", "p", "<b>")}
    assert rows(e.evidence(Not(Eq(ID, "p")), v)) == {("<b>", "p", "<c>")}


def test_shared_ends(spark):
    g = TripleGraph.from_rows(spark, [("<a>", "friend", "<x>"), ("<a>", "colleague", "<x>"), ("<a>", "friend", "<y>"), ("<b>", "friend", "<x>")])
    e = Engine(g)
    shape = ~Disj(Prop("friend"), "colleague")
    assert rows(e.subgraph(shape)) == {("<a>", "friend", "<x>"), ("<a>", "colleague", "<x>")}
    assert rows(e.evidence(shape, g.nodes(), tagged=True)) == {("<a>", "<a>", "friend", "<x>"), ("<a>", "<a>", "colleague", "<x>")}


def test_star_path_on_a_cycle(spark):
    g = TripleGraph.from_rows(spark, [("<a>", "q", "<b>"), ("<b>", "r", "<a>"), ("<b>", "r", "<c>"), ("<c>", "q", "<d>")])
    e = Engine(g)
    found = pairs(g, parse_path("(q/r)*"), e.node_set(["<a>"]))
    assert {r["x"] for r in found.collect()} == {"<a>", "<c>"}
    assert rows(trace_sets(g, parse_path("(q/r)*"), e.node_set(["<a>"]), e.node_set(["<c>"]))) == {("<a>", "q", "<b>"), ("<b>", "r", "<a>"), ("<b>", "r", "<c>")}


def test_vocabulary_loops_agree_with_rounds(spark):
    """Ring, chain and an isolated class, from both ends, with and without focus nodes, by closure and by rounds."""
    links = [("<c1>", "sub", "<c2>"), ("<c2>", "sub", "<c3>"), ("<c3>", "sub", "<c1>"), ("<c3>", "sub", "<c4>"), ("<x>", "type", "<c1>"), ("<y>", "type", "<c4>"), ("<z>", "type", "<lone>")]
    slow = TripleGraph.from_rows(spark, links)
    fast = TripleGraph(spark, slow.parts, frozenset({"sub"}))
    v, x = Engine(slow).node_set(["<x>", "<y>", "<z>"]), Engine(slow).node_set(["<c4>", "<lone>"])
    for text in ("type/sub*", "type/(^sub|sub)*", "type/(sub/sub)*", "sub*"):
        e = parse_path(text)
        assert rows(pairs(fast, e, v)) == rows(pairs(slow, e, v))
        assert rows(sources_of(fast, e, x)) == rows(sources_of(slow, e, x))
        assert rows(trace_sets(fast, e, v, x)) == rows(trace_sets(slow, e, v, x))
    e = parse_path("type/sub*")
    assert rows(pairs(fast, e, v)) == {("<x>", f"<c{i}>") for i in range(1, 5)} | {("<y>", "<c4>"), ("<z>", "<lone>")}
    assert rows(trace_from(fast, e, v)) == rows(trace_from(slow, e, v))


def test_comparisons_and_tags(spark):
    g = TripleGraph.from_rows(spark, [("<a>", "low", '"1"^^integer'), ("<a>", "high", '"2.5"^^decimal'), ("<b>", "low", '"x"'), ("<b>", "high", '"2"^^integer'), ("<a>", "t", '"u"@en'), ("<a>", "t", '"v"@EN'), ("<b>", "t", '"u"@de')])
    e, v = Engine(g), Engine(g).node_set(["<a>", "<b>"])
    assert nodes(e.conform(less_than("low", "high"), v)) == {"<a>"}
    assert rows(e.evidence(~less_than("low", "high"), v)) == {("<b>", "low", '"x"'), ("<b>", "high", '"2"^^integer')}
    assert nodes(e.conform(UniqueLang(Prop("t")), v)) == {"<b>"}
    assert len(rows(e.evidence(~UniqueLang(Prop("t")), v))) == 2
    assert nodes(e.conform(Closed(frozenset({"low", "high", "t"})), v)) == {"<a>", "<b>"}


def test_absent_node_target_is_reported(papers):
    e = Engine(papers, ShapeSchema([ShapeDef("S", some("author"), HasValue("<nobody>"))]))
    assert {r["focus"] for r in e.report().collect()} == {"<nobody>"}


def test_normal_form_and_simplification():
    s = ~(AtLeast(2, Prop("p"), checked("iri")) & ForAll(Prop("q"), TOP))
    assert to_nnf(s) == AtMost(1, Prop("p"), checked("iri")) | AtLeast(1, Prop("q"), BOTTOM)
    assert negate(AtLeast(0, Prop("p"), TOP)) == BOTTOM
    assert simplify(ForAll(Prop("p"), TOP)) == ForAll(Prop("p"), TOP) and simplify(ForAll(Prop("p"), TOP), False) == TOP


def test_schema_checks():
    with pytest.raises(ValueError):
        ShapeSchema([ShapeDef("A", HasShape("B")), ShapeDef("B", ~HasShape("A"))]).check()
    with pytest.raises(ValueError):
        ShapeSchema([ShapeDef("A", TOP), ShapeDef("A", TOP)]).check()
    assert ShapeSchema().lookup("unknown") == TOP
    got = ShapeSchema.from_json('[{"name": "A", "shape": {"atLeast": [1, "a/^b*", "top"]}, "target": {"class": "C"}}]')
    assert path_text(got.defs[0].shape.path) == "a/^(b)*" or path_text(got.defs[0].shape.path) == "a/^((b)*)"


def test_automaton():
    assert compile_path(path("type", "subClassOf*")).order() is None
    a = compile_path(Inv(parse_path("a/b")))
    assert a.order() is not None and a.leaves == (("b", True), ("a", True))


def test_engines_and_audits_agree(papers):
    shape = all_of(some("author", class_target("Student")), class_target("Paper"))
    e = Engine(papers)
    assert rows(run_sql(papers, sql_subgraph([shape], closure=closures(papers)))) == rows(e.subgraph(shape))
    assert audit_sufficiency(papers, [shape]).count() == 0 and audit_subgraph(papers, e.subgraph(shape)).count() == 0
    assert audit_schema(papers, ShapeSchema([ShapeDef("P", some("author"), class_target("Paper"))])).count() == 0
    pattern = node(leaf("author", value="<bob>"), classes=("Paper",))
    assert rows(pattern_images(papers, pattern)) == rows(e.subgraph(pattern_to_shape(pattern)))


def test_star_window(papers):
    shape = all_of(exactly(1, Prop("author")), ForAll(Prop("author"), checked("iri")))
    assert is_star(shape)
    target = Engine(papers).resolve(class_target("Paper"))
    bad, found = validate_and_extract_star(papers, shape, target)
    assert nodes(bad) == {"<p1>"} and rows(found) == {("<p2>", "author", "<ann>")}


def test_properties_without_the_targets_kind_are_left_out(spark):
    data = "/root/testdata/sf0.001"
    for name in ("B-Nation-neg", "B-Document-neg"):
        klass, shape = profile_shapes()[name]
        request = all_of(class_target(klass), shape)
        g = build_graph(spark, data)
        e = Engine(g)
        kinds, found = e.kinds_of(to_nnf(request)), e.subgraph(request)
        assert kinds == {f"<{'doc' if klass == 'Document' else 'nation'}/"} and not set(g.about(kinds).parts) & {"hasLine", "flag", "next", "url", "balance"}
        whole = TripleGraph(spark, g.parts, g.vocabulary, g.bags)
        assert rows(found) == rows(Engine(whole).subgraph(request)) and found.count()


def test_kinds_of_subjects_are_those_of_the_tables(spark):
    g = build_graph(spark, "/root/testdata/sf0.001")
    assert set(g.kinds.subjects) == set(g.parts) - {"type"}
    for p, known in g.kinds.subjects.items():
        assert {"<" + r[0] + "/" for r in g.prop(p).selectExpr("regexp_extract(s, '^<([a-z]+)/', 1)").distinct().collect()} <= known
    held = {tuple(r) for r in g.prop("type").selectExpr("o", "concat(regexp_extract(s, '^<[a-z]+/', 0))").distinct().collect()}
    assert all(g.kinds.instances(c) == {k} for c, k in held)


def test_translation_reads_no_universe_beside_a_target(spark):
    request = all_of(AtMost(0, Prop("hasLine"), TOP), class_target("Order"))
    assert "universe" not in sql_subgraph([request], closure=lambda e: "closure")
    g = relevant(build_graph(spark, "/root/testdata/sf0.001"), request)
    assert {r["o"] for r in g.prop("type").select("o").distinct().collect()} == {"<class/Order>"} and set(g.parts) == {"type", "subClassOf", "hasLine"}
    closed = relevant(build_graph(spark, "/root/testdata/sf0.001"), SHAPES["E13n"])
    assert set(closed.parts) == {"type", "subClassOf", "quality", "toxic"}


def test_images_hold_no_whole_solutions(spark, monkeypatch):
    """400 pages that link to one path make 160,000 solutions, and 1,200 triples."""
    monkeypatch.setattr(patterns, "_solutions", None)
    g = TripleGraph.from_rows(spark, [(f"<page/{i}>", p, o) for i in range(400) for p, o in (("linksTo", "<path/a>"), ("title", f'"{i}"'), ("type", "<class/Page>"))])
    found = pattern_images(g, node(leaf("title"), Edge("linksTo", node(leaf("^linksTo"))), classes=("Page",)))
    assert found.count() == 1200


def test_triples_about_a_kind_leave_other_tables_out(spark):
    g = build_graph(spark, "/root/testdata/sf0.001").about(frozenset({"<region/"}))
    assert {f.rsplit("/", 1)[1] for p in ("type", "name") for f in g.raw(p).inputFiles()} == {"region.parquet"}
    assert rows(g.prop("type")) == {(f"<region/{i}>", "<class/Region>") for i in range(5)}


def test_implied_conjuncts_and_own_triples_are_read_once(spark):
    """The class target implies two atoms; own triples are dealt once by subject and repeated rows appear once."""
    shape = to_nnf(all_of(class_target("Order"), profile_shapes()["B-Order-neg"][1]))
    assert len(unimplied(conjuncts(shape))) == 2
    assert unimplied([some("p"), Not(Closed(frozenset({"p"}))), Not(Disj(Prop("q"), "q"))]) == [some("p"), Not(Closed(frozenset({"p"}))), Not(Disj(Prop("q"), "q"))]
    base = TripleGraph.from_rows(spark, [("<order/1>", "type", "<class/Order>"), ("<order/1>", "status", '"F"'), ("<order/1>", "hasLine", "<line/1>"), ("<order/2>", "status", '"O"'), ("<line/1>", "type", "<class/LineItem>")])
    twice = {p: base.parts[p].union(base.parts[p]) for p in base.parts}
    classes = local(spark, [("<class/Order>", "<class/Thing>")], s=pa.string(), o=pa.string())
    g = TripleGraph(spark, {**base.parts, "subClassOf": classes}, frozenset({"subClassOf"}), twice, kinds())
    found = Engine(g).subgraph(shape)
    assert sorted(map(tuple, found.collect())) == [("<order/1>", "hasLine", "<line/1>"), ("<order/1>", "status", '"F"'), ("<order/1>", "type", "<class/Order>")]


def test_small_rounds_of_a_loop_are_not_written(spark, monkeypatch):
    """A chain of 12 steps and 5 side branches: few cuts while the driver holds the rounds, and the same nodes in any way."""
    chain = [(f"<n{i}>", "to", f"<n{i + 1}>") for i in range(12)] + [(f"<n{i}>", "to", f"<m{i}-{j}>") for i in (3, 6) for j in range(5)]
    g, cuts = TripleGraph.from_rows(spark, chain), []
    monkeypatch.setattr(reach, "cut", lambda df, tag="cut": cuts.append(tag) or cut(df, tag))
    found, loop = {}, parse_path("to*")
    for few, most in ((1_000, 200_000), (3, 200_000), (1_000, 4), (0, 0)):
        monkeypatch.setattr(reach, "FEW", few)
        monkeypatch.setattr(reach, "MOST_CLOSURE", most)
        cuts.clear()
        found[few, most] = {r["x"] for r in reach.pairs(g, loop, local(spark, [("<n0>",)], v=pa.string())).collect()}
        assert len(cuts) < 3 or few < 1_000 or most < 5
    assert set(map(len, found.values())) == {23} and len(set(map(frozenset, found.values()))) == 1


def test_hub_is_the_part_in_most_orders(spark, tmp_path):
    """Part 7 has most lines but few orders; parts 2 and 5 tie."""
    rows = [(1, 7)] * 5 + [(2, 7)] + [(i, 5) for i in range(3)] + [(i, 2) for i in range(3)] + [(9, 1)]
    local(spark, rows, l_orderkey=pa.int64(), l_partkey=pa.int64()).write.parquet(f"{tmp_path}/lineitem.parquet")
    assert hub(str(tmp_path), spark) == "<part/2>"


def test_shared_language_tags_need_no_pairs(spark, monkeypatch):
    """400 pages that link to one path make 160,000 pairs; verdict and evidence come from a range per node and tag."""
    g = TripleGraph.from_rows(spark, [(f"<page/{i}>", p, o) for i in range(400) for p, o in (("linksTo", "<path/a>"), ("title", f'"{i}"@{"en" if i < 398 else "de" if i < 399 else "fr"}'))] + [("<page/x>", "linksTo", "<path/b>"), ("<page/x>", "title", '"x"@en')])
    shape, e = Not(UniqueLang(path("linksTo", "^linksTo", "title"))), Engine(g)
    tagged = rows(e.evidence(shape, e.resolve(shape), tagged=True).select("s", "p", "o"))
    monkeypatch.setattr(evidence, "pairs", None)
    monkeypatch.setattr(evidence, "trace_pairs", None)
    assert nodes(e.resolve(shape)) == {f"<page/{i}>" for i in range(400)}
    found = e.subgraph(shape)
    assert rows(found) == tagged and found.count() == 400 + 398


def lines_repeated(spark, path):
    """The small tables, with lines that repeat, and one whose copy differs in what its node's term does not tell."""
    data = "/root/testdata/sf0.001"
    for f in os.listdir(data):
        if f != "lineitem.parquet":
            os.symlink(f"{data}/{f}", f"{path}/{f}")
    lines = spark.read.parquet(f"{data}/lineitem.parquet")
    other = lines.limit(40).withColumn("l_linestatus", F.when(F.col("l_linestatus") == "F", "O").otherwise("F"))
    lines.union(lines.limit(300)).union(other).coalesce(1).write.parquet(f"{path}/lineitem.parquet")
    return str(path)


@pytest.mark.parametrize("name", ["E11n", "E14", "E2", "E4", "E4n"])
def test_translated_evidence_of_repeated_lines(spark, tmp_path, name):
    """Bags, rows of a table, sieves and parts written first give the engine's evidence, each triple once."""
    d = lines_repeated(spark, tmp_path)
    found = [tuple(r) for r in Q[f"sql_{name}"](spark, d).collect()]
    assert len(found) == len(set(found)) and set(found) == rows(Engine(build_graph(spark, d)).subgraph(SHAPES[name]))


def test_translation_writes_no_whole_properties(spark, monkeypatch):
    """Lines are read where they lie: no property of theirs is written, and steps that meet in a line need no join."""
    g, cuts = build_graph(spark, "/root/testdata/sf0.001"), []
    monkeypatch.setattr(sqlgen, "cut", lambda df, tag="cut": cuts.append((tag, df.count())) or cut(df, tag))
    for name in ("E11n", "E14", "E2", "E4", "E4n"):
        cuts.clear()
        own = relevant(g, SHAPES[name])
        run_sql(own, sql_subgraph([SHAPES[name]], closure=closures(own), rows=own.rows))
        assert all(n < 2_000 for _, n in cuts), (name, cuts)
    for name, steps in (("E14", "hasLine/lineStatus"), ("E2", "hasLine/ofPart"), ("E4", "^placedBy/hasLine/fromSupplier/inNation")):
        assert any(isinstance(x, sqlgen.InRow) for x in walk(sqlgen.Translator(None, g.rows).plan(parse_path(steps))))
    assert not any(isinstance(x, sqlgen.InRow) for x in walk(sqlgen.Translator(None, g.rows).plan(parse_path("^flag/quantity"))))


def test_late_lines_are_shuffled_once(spark):
    g = relevant(build_graph(spark, "/root/testdata/sf0.001"), SHAPES["E11n"])
    text = sql_subgraph([SHAPES["E11n"]], closure=closures(g), rows=g.rows)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = run_sql(g, text)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    keys = set(re.findall(r"Exchange hashpartitioning\((.*?), \d+\)", plan))
    assert keys and all("," not in k for k in keys), keys


def walk(e):
    yield e
    for inner in ("first", "second", "path"):
        if hasattr(e, inner):
            yield from walk(getattr(e, inner))
