"""Queries of the graph engine for the driver, and SQL on the base tables that says the same in other words."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions.terms import iri
from .measures import emulate_by_patterns, properties_of, shares
from .operators.audit import audit_schema, audit_subgraph, audit_sufficiency, compare_graphs
from .operators.evidence import Engine
from .operators.reach import above, pairs, sources_of, trace_pairs, trace_sets
from .operators.star import validate_and_extract_star
from .plans.paths import Alt, Inv, Opt, Path, Prop, Seq, parse_path, path, steps_of
from .plans.patterns import GraphQuery, PatternNode, as_query, bindings, pattern_images, pattern_to_shape, triple_pattern, why_not
from .plans.shapes import TOP, AtLeast, AtMost, Closed, Compare, Disj, Eq, ForAll, HasValue, Not, Shape, ShapeDef, ShapeSchema, UniqueLang, all_of, class_target, conjuncts, constants, exactly, reduce_tests, simplify, some, test, to_nnf
from .plans.sqlgen import closures, run_sql, sql_conform, sql_size, sql_subgraph
from .oracles import nodes_sql, pattern_sql, shape_sql
from .sources.graph import TripleGraph, cut, load_graph, save_graph
from .sources.mapping import build_graph, containing
from .streaming.events import drain, event_triples, keep_star, once_each, stream_table, window_counts
from .workloads import BEYOND, PAIRED, PATTERNS, SHAPES, SLICES, chain_request, contains_slice, hub, hub_request, profile_shapes

Query = Callable[[SparkSession, str], DataFrame]
Q: dict[str, Query] = {}
SQL: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


# Nodes and evidence of the worked shapes.

ORDER = "'<order/' || o_orderkey || '>'"
CUST = "'<cust/' || c_custkey || '>'"
LINE = "'<line/' || l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey || '-' || strftime(l_shipdate, '%Y%m%d') || '>'"
HOME = "select distinct o_custkey from orders join lineitem on l_orderkey = o_orderkey join supplier on s_suppkey = l_suppkey join customer on c_custkey = o_custkey where s_nationkey = c_nationkey"
E6_ORDERS = f"with l as (select distinct l_orderkey as ok, {LINE} as line, l_returnflag as flag from lineitem), good as (select ok from l group by ok having sum(case when flag <> 'R' then 1 else 0 end) <= 1)"
PROMO = f"with m as (select o_orderkey, {LINE} as line, p_partkey from orders join lineitem on l_orderkey = o_orderkey join part on p_partkey = l_partkey where split_part(p_type, ' ', 1) = 'PROMO')"
TYPED_CUSTOMERS = f"select {CUST} as s, 'type' as p, '<class/seg/' || c_mktsegment || '>' as o from good union all select distinct '<class/seg/' || c_mktsegment || '>', 'subClassOf', '<class/Customer>' from good"
LATE = f"with m as (select distinct {LINE} as line, {ORDER} as ord, cast(o_orderdate as date) as od, cast(l_shipdate as date) as sd from lineitem join orders on o_orderkey = l_orderkey where cast(o_orderdate as date) >= cast(l_shipdate as date))"
NODES_SQL = {
    "E2": f"{PROMO} select distinct {ORDER} as v from m",
    "E3": f"select {CUST} as v from customer",
    "E4": f"select '<cust/' || o_custkey || '>' as v from ({HOME})",
    "E4n": f"select {CUST} as v from customer where c_custkey not in ({HOME})",
    "E5": "select '<doc/' || min(doc_id) || '>' as v from documents group by text",
    "E6": f"{E6_ORDERS} select '<order/' || ok || '>' as v from good",
    "E9": f"select {ORDER} as v from orders where o_orderkey not in (select l_orderkey from lineitem where l_linestatus <> 'F')",
    "E10": f"select {CUST} as v from customer where c_custkey not in (select o_custkey from orders group by o_custkey having count(*) > 5)",
    "E11": f"select distinct {LINE} as v from lineitem join orders on o_orderkey = l_orderkey where cast(o_orderdate as date) < cast(l_shipdate as date)",
    "E11n": f"select distinct {LINE} as v from lineitem join orders on o_orderkey = l_orderkey where cast(o_orderdate as date) >= cast(l_shipdate as date)",
    "E13": "select '<doc/' || doc_id || '>' as v from documents where doc_id not in (select doc_id from labels)",
    "E13n": "select '<doc/' || doc_id || '>' as v from labels",
    "E14": f"select {ORDER} as v from orders join (select l_orderkey, count(distinct l_linestatus) as n, min(l_linestatus) as st from lineitem group by l_orderkey) on l_orderkey = o_orderkey where n = 1 and st = o_orderstatus",
    "E15": "select '<turn/' || c.conv_id || '-' || c.turn || '>' as v from conversations c where exists (select 1 from conversations d where d.conv_id = c.conv_id and d.turn <= c.turn and d.role = 'system')",
}
EVIDENCE_SQL = {
    "E2": f"{PROMO} select distinct {ORDER} as s, 'type' as p, '<class/Order>' as o from m union select {ORDER}, 'hasLine', line from m union select line, 'ofPart', '<part/' || p_partkey || '>' from m union select '<part/' || p_partkey || '>', 'type', '<class/part/PROMO>' from m",
    "E3": f"with good as (select * from customer) {TYPED_CUSTOMERS} union all select {CUST}, 'inNation', '<nation/' || c_nationkey || '>' from good union all select '<nation/' || n_nationkey || '>', 'name', '\"' || n_name || '\"' from nation where n_nationkey in (select c_nationkey from good)",
    "E4": f"with m as (select c_custkey, c_mktsegment, c_nationkey, o_orderkey, {LINE} as line, s_suppkey from orders join lineitem on l_orderkey = o_orderkey join supplier on s_suppkey = l_suppkey join customer on c_custkey = o_custkey where s_nationkey = c_nationkey), good as (select distinct c_custkey, c_mktsegment, c_nationkey from m) {TYPED_CUSTOMERS} union all select {CUST}, 'inNation', '<nation/' || c_nationkey || '>' from good union all select distinct {ORDER}, 'placedBy', {CUST} from m union all select distinct {ORDER}, 'hasLine', line from m union all select distinct line, 'fromSupplier', '<supp/' || s_suppkey || '>' from m union all select distinct '<supp/' || s_suppkey || '>', 'inNation', '<nation/' || c_nationkey || '>' from m",
    "E4n": f"with good as (select * from customer where c_custkey not in ({HOME})) {TYPED_CUSTOMERS}",
    "E11": f"select v as s, 'type' as p, '<class/LineItem>' as o from ({NODES_SQL['E11']})",
    "E11n": f"{LATE} select line as s, 'type' as p, '<class/LineItem>' as o from m union select ord, 'hasLine', line from m union select ord, 'orderedOn', '\"' || strftime(od, '%Y-%m-%d') || '\"^^date' from m union select line, 'shippedOn', '\"' || strftime(sd, '%Y-%m-%d') || '\"^^date' from m",
    "E13": f"select v as s, 'type' as p, '<class/Document>' as o from ({NODES_SQL['E13']})",
    "E13n": f"select v as s, 'type' as p, '<class/Document>' as o from ({NODES_SQL['E13n']}) union all select '<doc/' || doc_id || '>', 'quality', '\"' || quality || '\"^^integer' from labels union all select '<doc/' || doc_id || '>', 'toxic', '\"' || toxic || '\"^^integer' from labels",
    "E14": f"with good as ({NODES_SQL['E14']}), l as (select distinct {ORDER} as v, {LINE} as line, l_linestatus as st, o_orderstatus as os from lineitem join orders on o_orderkey = l_orderkey), m as (select l.* from l join good on good.v = l.v) select distinct v as s, 'type' as p, '<class/Order>' as o from m union select v, 'status', '\"' || os || '\"' from m union select v, 'hasLine', line from m union select line, 'lineStatus', '\"' || st || '\"' from m",
    "E15": "with t as (select conv_id, turn, role, lag(turn) over (partition by conv_id order by turn) as previous, min(case when role = 'system' then turn end) over (partition by conv_id) as first_system from conversations) select '<turn/' || conv_id || '-' || turn || '>' as s, 'role' as p, '\"system\"' as o from t where role = 'system' union select '<turn/' || conv_id || '-' || turn || '>', 'replyTo', '<turn/' || conv_id || '-' || previous || '>' from t where turn > first_system",
    "E6": f"{E6_ORDERS} select '<order/' || ok || '>' as s, 'type' as p, '<class/Order>' as o from good union all select '<order/' || l.ok || '>', 'hasLine', line from l join good on l.ok = good.ok union all select line, 'flag', '\"R\"' from l join good on l.ok = good.ok where flag = 'R'",
    "E5": "select '<doc/' || id || '>' as s, p, o from (select min(doc_id) as id from documents group by text), (select 'type' as p, '<class/Document>' as o union all select 'canonical', null) where o is not null union all select '<doc/' || min(doc_id) || '>', 'canonical', '<doc/' || min(doc_id) || '>' from documents group by text",
    "E9": f"with l as (select distinct l_orderkey as ok, {LINE} as line, l_linestatus as st from lineitem), good as (select o_orderkey as ok from orders where o_orderkey not in (select ok from l where st <> 'F')) select '<order/' || ok || '>' as s, 'type' as p, '<class/Order>' as o from good union all select '<order/' || l.ok || '>', 'hasLine', line from l join good on l.ok = good.ok union all select line, 'lineStatus', '\"F\"' from l join good on l.ok = good.ok",
    "E10": f"with good as (select c_custkey, c_mktsegment from customer where c_custkey not in (select o_custkey from orders group by o_custkey having count(*) > 5)) select {CUST} as s, 'type' as p, '<class/seg/' || c_mktsegment || '>' as o from good union all select distinct '<class/seg/' || c_mktsegment || '>', 'subClassOf', '<class/Customer>' from good",
}
for _name, _shape in SHAPES.items():
    query(f"conform_{_name}", NODES_SQL.get(_name) or nodes_sql(_shape))(lambda s, d, x=_shape: Engine(build_graph(s, d)).select_nodes(x))
    query(f"evidence_{_name}", EVIDENCE_SQL.get(_name) or shape_sql(_shape))(lambda s, d, x=_shape: Engine(build_graph(s, d)).subgraph(x))


query("conform_E1", f"select * from ({nodes_sql(PAIRED[0])}) union select * from ({nodes_sql(PAIRED[1])})")(lambda s, d: Engine(build_graph(s, d)).select_nodes(*PAIRED))
query("evidence_E1", shape_sql(*PAIRED))(lambda s, d: Engine(build_graph(s, d)).subgraph(*PAIRED))
CHAINED = f"e as (select distinct l_orderkey as o, l_partkey as p from lineitem join orders on o_orderkey = l_orderkey where o_orderdate >= timestamp '{SLICES[0]}'), h as (select l_partkey as p from lineitem group by l_partkey order by count(distinct l_orderkey) desc, l_partkey limit 1), r(o) as (select o from e where p in (select p from h) union select b.o from r join e a on a.o = r.o join e b on b.p = a.p)"


@query("conform_E8_cyclic", f"with recursive {CHAINED} select '<order/' || o || '>' as v from r")
def chained_nodes(s: SparkSession, d: str) -> DataFrame:
    return Engine(contains_slice(build_graph(s, d), SLICES[0]).cached()).select_nodes(chain_request(hub(d, s)))


@query("evidence_E8_cyclic", f"with recursive {CHAINED} select '<order/' || o || '>' as s, 'contains' as p, '<part/' || p || '>' as o from e where o in (select o from r)")
def chained(s: SparkSession, d: str) -> DataFrame:
    return Engine(contains_slice(build_graph(s, d), SLICES[0]).cached()).subgraph(chain_request(hub(d, s)))


@query("evidence_tagged_E6", f"{E6_ORDERS} select '<order/' || ok || '>' as v, '<order/' || ok || '>' as s, 'type' as p, '<class/Order>' as o from good union all select '<order/' || l.ok || '>', '<order/' || l.ok || '>', 'hasLine', line from l join good on l.ok = good.ok union all select '<order/' || l.ok || '>', line, 'flag', '\"R\"' from l join good on l.ok = good.ok where flag = 'R'")
def evidence_tagged(s: SparkSession, d: str) -> DataFrame:
    e = Engine(build_graph(s, d))
    return e.evidence(SHAPES["E6"], e.resolve(SHAPES["E6"]), tagged=True)


def relevant(g: TripleGraph, shape: Shape) -> TripleGraph:
    """The triples that can matter for a shape with a class target among its conjuncts: type triples of the classes that it
    names, and what only its own ``closed`` asks for as far as its target's kind of node has it."""
    parts = conjuncts(to_nnf(shape))
    closed = [p for p in parts if isinstance(p, Closed) or (isinstance(p, Not) and isinstance(p.shape, Closed))]
    named = set().union(*(properties_of(p, set(g.parts)) for p in parts if p not in closed))
    kinds = Engine(g).kinds_of(to_nnf(shape))
    own = (properties_of(shape, set(g.parts)) & set(g.parts)) - named
    kept = {p: g.prop(p) for p in sorted(named) if p in g.parts}
    bags = {p: g.raw(p) for p in kept if p in g.bags}
    kept |= g.restrict(own).parts if kinds is None else g.restrict(own).about(kinds).parts
    classes = class_lists(g, to_nnf(shape))
    if kinds is not None and classes is not None and "type" in named:
        kept["type"], bags["type"] = (x.where(F.col("o").isin(sorted(classes))) for x in (g.prop("type"), g.raw("type")))
    return TripleGraph(g.spark, kept, g.vocabulary, bags, g.kinds, rows=g.rows)


def class_lists(g: TripleGraph, s: Shape) -> set[str] | None:
    """The classes below those that the shape names; None if it asks for types otherwise."""
    out: set[str] = set()
    if isinstance(s, AtLeast | AtMost | ForAll) and "type" in steps_of(s.path) or getattr(s, "prop", "") == "type" or isinstance(s, UniqueLang | Eq | Disj | Compare) and "type" in steps_of(s.path):
        found = above(g, s.path, s.shape.node) if isinstance(s, AtLeast) and isinstance(s.shape, HasValue) else None
        return None if found is None or found[0] != "type" else set(found[2])
    for inner in ("left", "right", "shape"):
        if hasattr(s, inner):
            below = class_lists(g, getattr(s, inner))
            if below is None:
                return None
            out |= below
    return out


def _translated(s: SparkSession, d: str, shape: Shape, evidence: bool) -> DataFrame:
    """One generated text over the shape's own properties; a loop over other data than classes is closed over those only."""
    g = build_graph(s, d)
    g = relevant(g, shape)
    make = sql_subgraph([shape], closure=closures(g), rows=g.rows) if evidence else sql_conform(shape, closure=closures(g), rows=g.rows)
    return run_sql(g, make, constants(shape))


#: E8 closes a loop over all lines, which the translation would do for every node of the graph.
for _name in [x for x in SHAPES if x != "E8"]:
    query(f"sql_{_name}", SQL[f"evidence_{_name}"])(lambda s, d, x=SHAPES[_name]: _translated(s, d, x, True))
for _name in ("E3", "E6", "E11", "E14"):
    query(f"sql_conform_{_name}", SQL[f"conform_{_name}"])(lambda s, d, x=SHAPES[_name]: _translated(s, d, x, False))


def order_schema() -> ShapeSchema:
    order, line = class_target("Order"), class_target("LineItem")
    return ShapeSchema([ShapeDef("OrderCard", all_of(some("placedBy"), some("hasLine")), order), ShapeDef("LineCard", all_of(some("ofPart"), some("fromSupplier"), ForAll(Prop("quantity"), test("datatype", "decimal"))), line)])


@query("validate_orders", f"select 'OrderCard' as shape, {ORDER} as focus from orders where o_orderkey not in (select l_orderkey from lineitem)")
def validate_orders(s: SparkSession, d: str) -> DataFrame:
    return Engine(build_graph(s, d), order_schema()).report().select("shape", "focus")


@query("validate_detail", f"select 'OrderCard' as shape, {ORDER} as focus, 'AtLeast' as component, 'hasLine' as path, '1' as value, 'does not conform' as message from orders where o_orderkey not in (select l_orderkey from lineitem)")
def validate_detail(s: SparkSession, d: str) -> DataFrame:
    return Engine(build_graph(s, d), order_schema()).report(detail=True)


@query("schema_subgraph_orders", shape_sql(*order_schema().requests()))
def schema_subgraph(s: SparkSession, d: str) -> DataFrame:
    return Engine(build_graph(s, d), order_schema()).schema_subgraph()


@query("fused_orders_report", SQL["validate_orders"])
def fused_report(s: SparkSession, d: str) -> DataFrame:
    return Engine(build_graph(s, d), order_schema()).validate_and_extract()[0].select("shape", "focus")


@query("fused_orders_subgraph", SQL["schema_subgraph_orders"])
def fused_subgraph(s: SparkSession, d: str) -> DataFrame:
    return Engine(build_graph(s, d), order_schema()).validate_and_extract()[1]


STAR = all_of(exactly(1, Prop("name")), some("balance"), ForAll(Prop("balance"), test("min", 0)), exactly(1, Prop("inNation")))


@query("star_customer_subgraph", f"with good as (select * from customer where c_acctbal >= 0) select {CUST} as s, 'name' as p, '\"' || c_name || '\"' as o from good union all select {CUST}, 'balance', '\"' || cast(cast(c_acctbal as decimal(18,2)) as varchar) || '\"^^decimal' from good union all select {CUST}, 'inNation', '<nation/' || c_nationkey || '>' from good")
def star_subgraph(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    return validate_and_extract_star(g, STAR, Engine(g).resolve(class_target("Customer")))[1]


@query("star_customer_report", f"select {CUST} as v from customer where c_acctbal < 0")
def star_report(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    return validate_and_extract_star(g, STAR, Engine(g).resolve(class_target("Customer")))[0]


for _name, (_klass, _shape) in profile_shapes().items():
    query(f"profile_{_name}", shape_sql(all_of(class_target(_klass), _shape)))(lambda s, d, x=_shape, k=_klass: Engine(build_graph(s, d)).subgraph(all_of(class_target(k), x)))


# Paths.

CONTAINS = "select distinct l_orderkey as o, l_partkey as p from lineitem"
PATHS: dict[str, tuple[Path, str, str]] = {
    "prop": (Prop("placedBy"), "Order", f"select {ORDER} as v, '<cust/' || o_custkey || '>' as x from orders"),
    "inverse": (Inv(Prop("placedBy")), "Customer", f"select '<cust/' || o_custkey || '>' as v, {ORDER} as x from orders"),
    "sequence": (path("placedBy", "inNation"), "Order", f"select {ORDER} as v, '<nation/' || c_nationkey || '>' as x from orders join customer on c_custkey = o_custkey"),
    "union": (Alt(Prop("placedBy"), Prop("status")), "Order", f"select {ORDER} as v, '<cust/' || o_custkey || '>' as x from orders union all select {ORDER}, '\"' || o_orderstatus || '\"' from orders"),
    "optional": (Opt(Prop("placedBy")), "Order", f"select {ORDER} as v, '<cust/' || o_custkey || '>' as x from orders union all select {ORDER}, {ORDER} from orders"),
    "star": (path("replyTo*"), "Turn", "select '<turn/' || c.conv_id || '-' || c.turn || '>' as v, '<turn/' || d.conv_id || '-' || d.turn || '>' as x from conversations c join conversations d on c.conv_id = d.conv_id and d.turn <= c.turn"),
    "nested": (Seq(Inv(Prop("inNation")), Opt(Inv(Prop("placedBy")))), "Nation", "select '<nation/' || c_nationkey || '>' as v, '<cust/' || c_custkey || '>' as x from customer union all select '<nation/' || s_nationkey || '>', '<supp/' || s_suppkey || '>' from supplier union all select '<nation/' || c_nationkey || '>', '<order/' || o_orderkey || '>' from customer join orders on o_custkey = c_custkey"),
}
for _name, (_path, _klass, _sql) in PATHS.items():
    query(f"path_{_name}", _sql)(lambda s, d, e=_path, k=_klass: pairs((g := build_graph(s, d)), e, Engine(g).resolve(class_target(k))))


@query("path_sources", "select '<order/' || o_orderkey || '>' as v from orders join customer on c_custkey = o_custkey where c_nationkey = 7")
def path_sources(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    return sources_of(g, path("placedBy", "inNation"), Engine(g).node_set(["<nation/7>"])).distinct()


@query("path_trace", "select '<order/' || o_orderkey || '>' as s, 'placedBy' as p, '<cust/' || o_custkey || '>' as o from orders join customer on c_custkey = o_custkey where c_nationkey = 7 union all select distinct '<cust/' || c_custkey || '>', 'inNation', '<nation/7>' from orders join customer on c_custkey = o_custkey where c_nationkey = 7")
def path_trace(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    e = Engine(g)
    return trace_sets(g, path("placedBy", "inNation"), e.resolve(class_target("Order")), e.node_set(["<nation/7>"]))


@query("path_trace_tagged", f"select {ORDER} as v, {ORDER} as s, 'placedBy' as p, '<cust/' || o_custkey || '>' as o from orders union all select {ORDER}, '<cust/' || o_custkey || '>', 'inNation', '<nation/' || c_nationkey || '>' from orders join customer on c_custkey = o_custkey")
def path_trace_tagged(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    e = path("placedBy", "inNation")
    return trace_pairs(g, e, pairs(g, e, Engine(g).resolve(class_target("Order"))))


# Tree patterns: the shape's subgraph, the pattern's images, and their comparison.

PATTERN_SQL = {
    "A5b": "select '<part/' || p_partkey || '>' as s, p, o from (select p_partkey, 'brand' as p, '<brand/17>' as o from part where p_brand = 'Brand#17' union all select p_partkey, 'type', '<class/part/' || split_part(p_type, ' ', 1) || '>' from part where p_brand = 'Brand#17') union all select distinct '<class/part/' || split_part(p_type, ' ', 1) || '>', 'subClassOf', '<class/Part>' from part where p_brand = 'Brand#17'",
    "A6a": "select '<order/' || o_orderkey || '>' as s, 'total' as p, '\"' || cast(cast(o_totalprice as decimal(18,2)) as varchar) || '\"^^decimal' as o from orders where o_totalprice > 400000 union all select '<order/' || o_orderkey || '>', 'type', '<class/Order>' from orders where o_totalprice > 400000",
    "A2a": f"select {ORDER} as s, 'type' as p, '<class/Order>' as o from orders union all select {ORDER}, 'placedBy', '<cust/' || o_custkey || '>' from orders union all select {CUST}, 'name', '\"' || c_name || '\"' from customer where c_custkey in (select o_custkey from orders)",
}

def equality_sql(images: str, evidence: str) -> str:
    """How the images of a pattern and the subgraph of its shape differ: triples missing from the subgraph, and further ones."""
    return f"select missing, extra, missing + extra = 0 as equal from (select (select count(*) from (select s, p, o from ({images}) except select s, p, o from ({evidence}))) as missing, (select count(*) from (select s, p, o from ({evidence}) except select s, p, o from ({images}))) as extra)"


def equality(g: TripleGraph, pattern: PatternNode) -> DataFrame:
    found = compare_graphs(pattern_images(g, pattern), Engine(g).subgraph(pattern_to_shape(pattern)))
    return found.select(F.col("missing").cast("long").alias("missing"), F.col("extra").cast("long").alias("extra"), "equal")


for _name, _pattern in PATTERNS.items():
    # An absent edge to a value leaves the node's other values in the evidence, so such a subgraph holds more than the images.
    _evidence, _images = PATTERN_SQL.get(_name) or shape_sql(pattern_to_shape(_pattern)), PATTERN_SQL.get(_name) or pattern_sql(_pattern)
    query(f"subgraph_{_name}", _evidence)(lambda s, d, x=_pattern: Engine(build_graph(s, d)).subgraph(pattern_to_shape(x)))
    query(f"images_{_name}", _images)(lambda s, d, x=_pattern: pattern_images(build_graph(s, d), x))
    query(f"measure_equality_{_name}", equality_sql(_images, _evidence))(lambda s, d, x=_pattern: equality(build_graph(s, d), x))


@query("bindings_A2a", "select '<order/' || o_orderkey || '>' as n, '<cust/' || c_custkey || '>' as n_0, '\"' || c_name || '\"' as n_0_0 from orders join customer on c_custkey = o_custkey")
def bindings_a2a(s: SparkSession, d: str) -> DataFrame:
    return bindings(build_graph(s, d), PATTERNS["A2a"]).select("n", "n_0", "n_0_0")


def order_query(pairs_: list[tuple[int, int]]) -> GraphQuery:
    """Orders that hold the same parts from the same suppliers: an order's lines (part, supplier) with variables for keys."""
    parts = sorted({p for p, _ in pairs_})
    return GraphQuery(tuple(("?order", "contains", f"?part{p}") for p in parts) + tuple((f"?supp{u}", "supplies", f"?part{p}") for p, u in pairs_))


ORDER_REASONS = "select case when count(distinct (l_partkey, l_suppkey)) > count(distinct l_suppkey) then 'cycle' else 'none' end as reason from lineitem where l_orderkey is not null and l_partkey is not null and l_suppkey is not null group by l_orderkey"


@query("measure_applicability", f"select reason, cast(sum(queries) as bigint) as queries from (select * from (values ('none', 39), ('property variable', 3), ('arithmetic', 2), ('counting', 1), ('cycle', 1)) t(reason, queries) union all select reason, count(*) from ({ORDER_REASONS}) group by reason) group by reason")
def applicability(s: SparkSession, d: str) -> DataFrame:
    """Why a query is no shape, from its atoms; ``none`` counts those that are shapes. Asked are the workload's queries and,
    of every order, the query that its lines make."""
    asked = [as_query(p) for p in PATTERNS.values()] + list(BEYOND.values())
    fixed = s.createDataFrame([(why_not(q) or "none",) for q in asked], "reason string")
    lines = table(s, d, "lineitem").where("l_orderkey is not null and l_partkey is not null and l_suppkey is not null")
    held = lines.groupBy("l_orderkey").agg(F.collect_set(F.struct("l_partkey", "l_suppkey")).alias("lines"))
    reason = F.udf(lambda rows: why_not(order_query(sorted((r[0], r[1]) for r in rows))) or "none", "string")
    return fixed.unionAll(held.select(reason("lines").alias("reason"))).groupBy("reason").agg(F.count("*").alias("queries"))


# Hub distance.

for _since in SLICES:
    def _hub(s: SparkSession, d: str, since: str = _since) -> DataFrame:
        g = contains_slice(build_graph(s, d), since)
        return Engine(g).subgraph(hub_request(hub(d, s)))

    _base = f"e as (select distinct l_orderkey as o, l_partkey as p from lineitem join orders on o_orderkey = l_orderkey where o_orderdate >= timestamp '{_since}'), h as (select l_partkey as p from lineitem group by l_partkey order by count(distinct l_orderkey) desc, l_partkey limit 1)"
    _steps = "p1 as (select distinct b.p from e a join e b on a.o = b.o where a.p in (select p from h)), p2 as (select distinct b.p from e a join e b on a.o = b.o where a.p in (select p from p1)), o3 as (select distinct o from e where p in (select p from p2))"
    query(f"hub_distance_{_since}", f"with {_base}, {_steps} select '<order/' || o || '>' as s, 'contains' as p, '<part/' || p || '>' as o from e where o in (select o from o3)")(_hub)


@query("measure_hub_shares", f"with {_base.replace(SLICES[-1], SLICES[0])}, {_steps}, n as (select count(*) as nodes from (select distinct p from e where o in (select o from o3))), t as (select count(*) as triples from e where o in (select o from o3)), w as (select count(distinct p) as all_nodes, count(*) as all_triples from e) select *, round(nodes / all_nodes, 6) as node_share, round(triples / all_triples, 6) as triple_share from n, t, w")
def hub_shares(s: SparkSession, d: str) -> DataFrame:
    g = contains_slice(build_graph(s, d), SLICES[0])
    request = hub_request(hub(d, s))
    e = Engine(g)
    return shares(e.subgraph(request), e.select_nodes(request), g, "contains")


@query("hub_distance_bucketed", SQL[f"hub_distance_{SLICES[0]}"])
def hub_bucketed(s: SparkSession, d: str) -> DataFrame:
    """The same request on the other stored layout: a catalog table partitioned by property and bucketed by object."""
    name = f"shapegraph_{uuid.uuid4().hex}"
    save_graph(contains_slice(build_graph(s, d), SLICES[0]), name, by="o")
    try:
        return cut(Engine(load_graph(s, name, ["contains"])).subgraph(hub_request(hub(d, s))), "bucketed")
    finally:
        s.sql(f"drop table {name}")


# Outside the shape language: answered natively.


@query("native_N1", "select '<order/' || o_orderkey || '>' as s, count(*) as facts from (select o_orderkey from orders where o_orderpriority = '1-URGENT' union all select o_orderkey from orders where o_orderpriority = '1-URGENT' union all select o_orderkey from orders where o_orderpriority = '1-URGENT' union all select o_orderkey from orders where o_orderpriority = '1-URGENT') group by o_orderkey")
def native_facts(s: SparkSession, d: str) -> DataFrame:
    """All facts of urgent orders whatever their property (of the order's own columns but its type)."""
    g = build_graph(s, d).restrict(["placedBy", "status", "total", "priority"])
    urgent = g.prop("priority").where(F.col("o") == '"1-URGENT"').select("s")
    return g.triples().join(urgent, "s", "left_semi").groupBy("s").agg(F.count("*").alias("facts"))


@query("native_N2", "select '<line/' || l_orderkey as s, 1 as x from lineitem where false")
def native_between(s: SparkSession, d: str) -> DataFrame:
    """Which property joins a supplier directly to a customer: none."""
    t = build_graph(s, d).restrict(["inNation", "supplies", "placedBy"]).triples()
    return t.where(F.col("s").startswith("<supp/") & F.col("o").startswith("<cust/")).select("s", F.lit(1).alias("x"))


@query("native_N3", "select 'inNation' as p, count(*) as pairs from customer c join supplier s on c_nationkey = s_nationkey")
def native_same(s: SparkSession, d: str) -> DataFrame:
    """Customer and supplier that share a value of the same property, counted per property and value before pairing."""
    g = build_graph(s, d)
    t = g.restrict(["inNation", "name"]).triples()
    sides = t.groupBy("p", "o").agg(F.sum(F.col("s").startswith("<cust/").cast("long")).alias("c"), F.sum(F.col("s").startswith("<supp/").cast("long")).alias("u"))
    return sides.where("c > 0 and u > 0").groupBy("p").agg(F.sum(F.col("c") * F.col("u")).alias("pairs"))


@query("native_N4", f"select distinct {LINE} as v from lineitem where cast(l_extendedprice as decimal(18,2)) * (1 - cast(l_discount as decimal(18,2))) > 90000")
def native_revenue(s: SparkSession, d: str) -> DataFrame:
    line = table(s, d, "lineitem")
    from .sources.mapping import line_iri

    value = F.col("l_extendedprice").cast("decimal(18,2)") * (1 - F.col("l_discount").cast("decimal(18,2)"))
    return line.where(value > 90000).select(line_iri().alias("v")).distinct()


@query("native_N5", f"select {ORDER} as v from orders join (select l_orderkey, sum(cast(l_extendedprice as decimal(18,2))) as t from lineitem group by l_orderkey) on l_orderkey = o_orderkey where t < cast(o_totalprice as decimal(18,2))")
def native_totals(s: SparkSession, d: str) -> DataFrame:
    sums = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("t"))
    joined = table(s, d, "orders").join(sums, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.where(F.col("t") < F.col("o_totalprice").cast("decimal(18,2)")).select(F.concat(F.lit("<order/"), "o_orderkey", F.lit(">")).alias("v"))


@query("native_N6", f"select {CUST} as v from customer left join orders on o_custkey = c_custkey group by c_custkey having sum(case when o_orderstatus = 'F' then 1 else 0 end) >= sum(case when o_orderstatus = 'O' then 1 else 0 end)")
def native_majority(s: SparkSession, d: str) -> DataFrame:
    o = table(s, d, "orders").groupBy("o_custkey").agg(F.sum((F.col("o_orderstatus") == "F").cast("int")).alias("f"), F.sum((F.col("o_orderstatus") == "O").cast("int")).alias("n"))
    c = table(s, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left")
    return c.where(F.coalesce("f", F.lit(0)) >= F.coalesce("n", F.lit(0))).select(F.concat(F.lit("<cust/"), "c_custkey", F.lit(">")).alias("v"))


@query("native_N7", "with e as (select a.p as a, b.p as b from (select distinct l_orderkey as o, l_partkey as p from lineitem) a join (select distinct l_orderkey as o, l_partkey as p from lineitem) b on a.o = b.o and a.p < b.p group by 1, 2 having count(*) > 1) select '<part/' || e1.a || '>' as a, '<part/' || e1.b || '>' as b, '<part/' || e2.b || '>' as c, '<part/' || e3.b || '>' as d from e e1 join e e2 on e2.a = e1.b join e e3 on e3.a = e2.b join e x on x.a = e1.a and x.b = e2.b join e y on y.a = e1.a and y.b = e3.b join e z on z.a = e1.b and z.b = e3.b")
def native_clique(s: SparkSession, d: str) -> DataFrame:
    """Four parts that each stand together in two or more orders; pairs only from the lines of one order."""
    c = table(s, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    e = c.toDF("o", "a").join(c.toDF("o", "b"), "o").where("a < b").groupBy("a", "b").count().where("count > 1").select("a", "b")
    e = cut(e, "clique")
    j = e.join(e.toDF("b", "c"), "b").join(e.toDF("a", "c"), ["a", "c"], "left_semi").join(e.toDF("c", "d"), "c").join(e.toDF("a", "d"), ["a", "d"], "left_semi").join(e.toDF("b", "d"), ["b", "d"], "left_semi")
    return j.select(*(F.concat(F.lit("<part/"), x, F.lit(">")).alias(x) for x in "abcd"))


# Triple patterns, audits, sizes.


@query("tpf_property", f"select {ORDER} as s, 'placedBy' as p, '<cust/' || o_custkey || '>' as o from orders")
def tpf_property(s: SparkSession, d: str) -> DataFrame:
    return triple_pattern(build_graph(s, d), p="placedBy")


@query("tpf_object", f"select {CUST} as s, 'inNation' as p, '<nation/7>' as o from customer where c_nationkey = 7 union all select '<supp/' || s_suppkey || '>', 'inNation', '<nation/7>' from supplier where s_nationkey = 7")
def tpf_object(s: SparkSession, d: str) -> DataFrame:
    return triple_pattern(build_graph(s, d), p="inNation", o="<nation/7>")


@query("tpf_as_shape", SQL["tpf_object"])
def tpf_as_shape(s: SparkSession, d: str) -> DataFrame:
    return Engine(build_graph(s, d)).subgraph(some("inNation", HasValue("<nation/7>")))


TYPED = ("customer", "supplier", "part", "orders", "events", "documents", "pages", "conversations", "benchmark", "region", "nation", "embeddings")
FETCHED = {
    "type": " + ".join(f"(select count(*) from {t})" for t in TYPED) + f" + (select count(distinct {LINE}) from lineitem)",
    "subClassOf": "16 + (select count(distinct split_part(p_type, ' ', 1)) from part)",
    "hasLine": f"(select count(distinct {LINE}) from lineitem)",
    "flag": f"(select count(*) from (select distinct {LINE}, l_returnflag from lineitem))",
}


@query("measure_requests", f"select 4 as requests, cast({' + '.join(FETCHED.values())} as bigint) as triples")
def requests(s: SparkSession, d: str) -> DataFrame:
    """Single-pattern requests that decide the shape, and the triples that they fetch."""
    found, n = emulate_by_patterns(build_graph(s, d), SHAPES["E6"])
    return found.agg(F.lit(n).alias("requests"), F.count("*").alias("triples"))


@query("measure_sql_size")
def sizes(s: SparkSession, d: str) -> DataFrame:
    """Length of each generated text, and the triples of the given tables that it is written over."""
    g = build_graph(s, d)
    rows, over = [], []
    for k in ("E3", "E6", "E9", "E10", "E5"):
        for kind, x in (("whole", SHAPES[k]), ("reduced", simplify(reduce_tests(SHAPES[k])))):
            n = sql_size(sql_subgraph([x], closure=lambda e: "closure"))
            rows.append((k, kind, n["lines"], n["characters"]))
            over += [(k, kind, p) for p in sorted(properties_of(x))]
    named = sorted({p for *_, p in over})
    counts = g.triples(named).groupBy("p").agg(F.count("*").alias("n"))
    sums = s.createDataFrame(over, "shape string, form string, p string").join(counts, "p").groupBy("shape", "form").agg(F.sum("n").alias("triples"))
    return s.createDataFrame(rows, "shape string, form string, lines int, characters int").join(sums, ["shape", "form"], "left").withColumn("triples", F.coalesce("triples", F.lit(0)))


@query("audit_sufficiency", "select cast(0 as bigint) as violations")
def audit1(s: SparkSession, d: str) -> DataFrame:
    return audit_sufficiency(build_graph(s, d), [SHAPES["E6"], SHAPES["E10"]]).agg(F.count("*").alias("violations"))


@query("audit_schema", "select cast(0 as bigint) as violations")
def audit2(s: SparkSession, d: str) -> DataFrame:
    return audit_schema(build_graph(s, d), ShapeSchema([ShapeDef("Nation", some("inRegion"), class_target("Nation"))])).agg(F.count("*").alias("violations"))


@query("audit_subgraph", "select cast(0 as bigint) as violations")
def audit3(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    return audit_subgraph(g.restrict(["type", "hasLine", "flag", "subClassOf"]), Engine(g).subgraph(SHAPES["E6"])).agg(F.count("*").alias("violations"))


# Relational operators around the methods: query -> (Spark SQL or DataFrame, the same in ANSI SQL).

SQL_OPERATORS = {
    "op_scan_pushdown": "select o_orderkey, o_totalprice from orders where o_totalprice > 400000",
    "op_predicates": "select p_partkey from part where p_size between 10 and 20 and p_brand in ('Brand#17', 'Brand#3')",
    "op_join_inner": "select o_orderkey, c_name from orders join customer on c_custkey = o_custkey",
    "op_join_left": "select d.doc_id, quality from documents d left join labels l on l.doc_id = d.doc_id",
    "op_join_full": "select coalesce(d.doc_id, l.doc_id) as doc_id, quality from documents d full join labels l on l.doc_id = d.doc_id",
    "op_join_semi": "select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey)",
    "op_join_anti": "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)",
    "op_join_theta": "select o_orderkey, count(*) as n from orders join lineitem on l_orderkey = o_orderkey and l_shipdate <= o_orderdate group by o_orderkey",
    "op_agg_partial_final": "select l_returnflag, l_linestatus, count(*) as n, sum(cast(l_quantity as decimal(18,2))) as quantity from lineitem group by l_returnflag, l_linestatus",
    "op_agg_distinct": "select l_returnflag, count(distinct l_partkey) as parts from lineitem group by l_returnflag",
    "op_rollup": "select r_name, n_name, count(*) as n from customer join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by rollup(r_name, n_name)",
    "op_cube": "select c_nationkey, c_mktsegment, count(*) as n from customer group by cube(c_nationkey, c_mktsegment)",
    "op_grouping_sets": "select c_nationkey, c_mktsegment, count(*) as n from customer group by grouping sets ((c_nationkey), (c_mktsegment))",
    "op_window_rank": "select event_id, row_number() over (partition by user_id order by ts, event_id) as rn from events",
    "op_window_lag": "select event_id, lag(event_type) over (partition by user_id order by ts, event_id) as before from events",
    "op_window_frame": "select event_id, count(*) over (partition by user_id order by ts, event_id rows between 2 preceding and current row) as n from events",
    "op_sort_limit": "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10",
    "op_topk_per_group": "select o_custkey, o_orderkey from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rn from orders) t where rn <= 2",
    "op_union": "select l_partkey as k from lineitem union select p_partkey from part",
    "op_intersect": "select o_orderkey as k from orders intersect select l_orderkey from lineitem",
    "op_except": "select o_orderkey as k from orders except select l_orderkey from lineitem",
    "op_set_equality": "select o_orderkey from orders join (select l_orderkey, count(distinct l_linestatus) as n, min(l_linestatus) as st from lineitem group by l_orderkey) t on l_orderkey = o_orderkey where n = 1 and st = o_orderstatus",
    "op_group_join": "select c_custkey, count(o_orderkey) as n from customer left join orders on o_custkey = c_custkey group by c_custkey",
    "op_string": "select page_id, lower(url) as u, length(url) as n from pages",
    "op_project_pruned": "select l_orderkey, l_quantity from lineitem where l_discount >= 0.05",
    "op_join_broadcast": "select /*+ BROADCAST(nation) */ c_custkey, n_name from customer join nation on n_nationkey = c_nationkey",
    "op_distinct": "select distinct l_partkey, l_suppkey from lineitem",
    "op_window_range": "select event_id, count(*) over (partition by user_id order by value range between 10 preceding and current row) as n from events",
    "op_math": "select p_partkey, p_size % 7 as r, abs(p_size - 25) as a from part",
}


def _sql_operator(text: str) -> Query:
    import re

    def run(s: SparkSession, d: str) -> DataFrame:
        names = set(re.findall(r"\b(?:from|join) (region|nation|customer|supplier|part|orders|lineitem|events|documents|embeddings|pages|benchmark|labels|conversations)\b", text))
        for n in names:
            table(s, d, n).createOrReplaceTempView(n)
        return s.sql(text)

    return run


for _name, _text in SQL_OPERATORS.items():
    query(_name, _text)(_sql_operator(_text))


@query("op_join_asof", "select p.event_id, (select max(e.event_id) from events e where e.user_id = p.user_id and e.event_type <> 'purchase' and (e.ts < p.ts or (e.ts = p.ts and e.event_id < p.event_id)) and not exists (select 1 from events f where f.user_id = e.user_id and f.event_type <> 'purchase' and (f.ts > e.ts or (f.ts = e.ts and f.event_id > e.event_id)) and (f.ts < p.ts or (f.ts = p.ts and f.event_id < p.event_id)))) as last_id from events p where p.event_type = 'purchase'")
def as_of(s: SparkSession, d: str) -> DataFrame:
    """The last other event of the user before each purchase: one window, no join."""
    e = table(s, d, "events")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_id", last).where("event_type = 'purchase'").select("event_id", "last_id")


@query("op_join_range", "select event_id, cast(floor(value / 50) as bigint) as band from events where value >= 0 and value < 500")
def range_join(s: SparkSession, d: str) -> DataFrame:
    """Events in value bands: an equi-join on the bucket, then the exact bounds."""
    bands = s.range(10).select(F.col("id").alias("band"), (F.col("id") * 50).alias("low"), ((F.col("id") + 1) * 50).alias("high"))
    e = table(s, d, "events").withColumn("bucket", F.floor(F.col("value") / 50))
    return e.join(F.broadcast(bands), e["bucket"] == bands["band"]).where("value >= low and value < high").select("event_id", "band")


@query("op_json", "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")
def json_field(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("op_explode", "select page_id, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) as path from pages")
def explode_links(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="(/[^"]*)"'), 1)).alias("path"))


@query("op_date", "select o_orderkey, strftime(o_orderdate, '%Y-%m') as month, cast(date_diff('day', date '1992-01-01', cast(o_orderdate as date)) as bigint) as days from orders")
def dates(s: SparkSession, d: str) -> DataFrame:
    since = F.date_diff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))
    return table(s, d, "orders").select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM").alias("month"), since.cast("long").alias("days"))


@query("op_array", "select vec_id, (select count(*) from unnest(embedding) t(u) where u > 0) as positive, cast(list_max(embedding) as double) as most from embeddings")
def arrays(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.array_max("embedding").cast("double").alias("most"))


@query("op_map", "select user_id, nullif(count(*) filter (where event_type = 'click'), 0) as clicks from events group by user_id")
def maps(s: SparkSession, d: str) -> DataFrame:
    counts = table(s, d, "events").where("event_type is not null").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    by_user = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))  # one entry per type
    return by_user.select("user_id", F.try_element_at("m", F.lit("click")).alias("clicks"))


@query("op_recursive_class", "select x from (values ('<class/event/error>'), ('<class/SystemEvent>'), ('<class/Event>'), ('<class/Thing>')) t(x)")
def recursive_class(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d).restrict(["subClassOf"])
    return pairs(g, parse_path("subClassOf*"), Engine(g).node_set(["<class/event/error>"])).select("x")


@query("op_recursive_reply", "select distinct '<turn/' || a.conv_id || '-' || a.turn || '>' as v, '<turn/' || b.conv_id || '-' || b.turn || '>' as x from conversations a join conversations b on a.conv_id = b.conv_id and b.turn <= a.turn")
def recursive_reply(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    turns = table(s, d, "conversations").select(iri("turn", "conv_id", "turn").alias("v")).distinct()
    return pairs(g.restrict(["replyTo"]), parse_path("replyTo*"), turns).select("v", "x")


@query("op_join_nested_loop", "select item_id, doc_id from benchmark b join documents d on contains(d.text, b.text)")
def containment(s: SparkSession, d: str) -> DataFrame:
    return containing(table(s, d, "documents"), table(s, d, "benchmark"))


query("op_majority", SQL["native_N6"])(Q["native_N6"])
query("op_four_clique", SQL["native_N7"])(Q["native_N7"])


@query("op_nodes", f"select {ORDER} as v from orders union select '<cust/' || o_custkey || '>' from orders")
def graph_nodes(s: SparkSession, d: str) -> DataFrame:
    return build_graph(s, d).restrict(["placedBy"]).nodes()


@query("op_graph_union", f"{SQL['tpf_property']} union select {ORDER}, 'priority', '\"' || o_orderpriority || '\"' from orders")
def graph_union(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    return g.restrict(["placedBy"]).union(g.restrict(["placedBy", "priority"])).triples()


@query("op_graph_minus", f"select {ORDER} as s, 'priority' as p, '\"' || o_orderpriority || '\"' as o from orders")
def graph_minus(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    return g.restrict(["placedBy", "priority"]).minus(g.restrict(["placedBy"])).triples()


# Streams: replayed events against SQL on the same rows.


@query("stream_tumbling", "select date_trunc('hour', ts) as start, event_type, count(*) as n from events group by 1, 2")
def tumbling(s: SparkSession, d: str) -> DataFrame:
    counts = window_counts(stream_table(s, d, "events"), F.window("ts", "1 hour"), "event_type")
    return drain(counts, "tumbling", "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("stream_sliding", "select date_trunc('hour', ts) - k * interval 1 hour as start, count(*) as n from events, (values (0), (1)) t(k) group by 1")
def sliding(s: SparkSession, d: str) -> DataFrame:
    counts = window_counts(stream_table(s, d, "events"), F.window("ts", "2 hours", "1 hour"))
    return drain(counts, "sliding", "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_session", "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hour then 0 else 1 end as fresh from events), h as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, min(ts) as start, count(*) as n from h group by user_id, k")
def session(s: SparkSession, d: str) -> DataFrame:
    counts = window_counts(stream_table(s, d, "events"), F.session_window("ts", "6 hours"), "user_id")
    return drain(counts, "session", "complete").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_once_each", "select distinct event_id from events")
def stream_distinct(s: SparkSession, d: str) -> DataFrame:
    return drain(once_each(stream_table(s, d, "events"), "event_id"), "once").select("event_id")


@query("stream_star", "select '<event/' || event_id || '>' as v, cast(2 as bigint) as n from events where value > 100")
def stream_star(s: SparkSession, d: str) -> DataFrame:
    """Events with a user and a value above 100, kept up to date, with their counts of evidence triples."""
    shape = some("byUser") & some("value", test("above", 100))
    seen = keep_star(event_triples(stream_table(s, d, "events")), shape, ["byUser", "value"])
    return seen.where("ok and evidence").groupBy("v").agg(F.count("*").alias("n"))


@query("op_degree", "with t as (select '<order/' || o_orderkey || '>' as s, '<cust/' || o_custkey || '>' as o from orders union all select distinct '<order/' || l_orderkey || '>', '<part/' || l_partkey || '>' from lineitem) select v, sum(a) as out_degree, sum(b) as in_degree from (select s as v, 1 as a, 0 as b from t union all select o, 0, 1 from t) group by v")
def degree(s: SparkSession, d: str) -> DataFrame:
    return build_graph(s, d).restrict(["placedBy", "contains"]).degrees()


@query("op_property_stats")
def stats(s: SparkSession, d: str) -> DataFrame:
    return build_graph(s, d).stats()


@query("op_graph_algebra", "select cast((select count(*) from orders) as bigint) as both_sides, cast(0 as bigint) as rest")
def algebra(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d)
    a, b = g.restrict(["placedBy", "status"]), g.restrict(["placedBy"])
    both = TripleGraph(s, a.intersect(b).parts)
    return both.triples().agg(F.count("*").alias("both_sides"), F.sum((F.col("p") != "placedBy").cast("long")).alias("rest"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Engine(build_graph(spark, sf_dir)).subgraph(SHAPES["E6"])


__all__ = ["AtMost", "Closed", "Compare", "Disj", "Q", "SQL", "Shape", "TOP", "flagship"]
