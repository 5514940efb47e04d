"""Tree patterns: their compilation to shapes, and their images and bindings by joins (the baselines)."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.evidence import Engine
from ..sources.graph import TripleGraph, cut
from .paths import Inv, Prop
from .shapes import TOP, AtLeast, AtMost, HasValue, NodeTest, Shape, Test, all_of, any_of, class_target


@dataclass(frozen=True)
class Edge:
    """A step from a node: property (``^`` turns it), the node behind it, and required, optional or absent."""

    prop: str
    node: PatternNode
    mode: str = "required"


@dataclass(frozen=True)
class PatternNode:
    edges: tuple[Edge, ...] = ()
    value: str | None = None
    test: NodeTest | None = None
    classes: tuple[str, ...] = ()


def node(*edges: Edge, value: str | None = None, test: tuple | None = None, classes: tuple[str, ...] = ()) -> PatternNode:
    return PatternNode(edges, value, NodeTest(*test) if test else None, classes)


def leaf(prop: str, mode: str = "required", **of) -> Edge:
    return Edge(prop, node(**of), mode)


def pattern_to_shape(n: PatternNode) -> Shape:
    parts: list[Shape] = []
    if n.classes:
        parts.append(any_of(*map(class_target, n.classes)))
    if n.value is not None:
        parts.append(HasValue(n.value))
    if n.test is not None:
        parts.append(Test(n.test))
    for e in n.edges:
        step = Inv(Prop(e.prop[1:])) if e.prop.startswith("^") else Prop(e.prop)
        inner = pattern_to_shape(e.node)
        parts.append(AtMost(0, step, inner) if e.mode == "absent" else AtLeast(int(e.mode == "required"), step, inner))
    return all_of(*parts) if parts else TOP


@dataclass(frozen=True)
class GraphQuery:
    """Atoms (subject, property, object), where ``?x`` is a variable; ``computed``: variables that one expression takes
    together; ``counted``: variables whose numbers of values are compared."""

    atoms: tuple[tuple[str, str, str], ...]
    computed: tuple[tuple[str, ...], ...] = ()
    counted: tuple[str, ...] = ()


def as_query(n: PatternNode, name: str = "?n") -> GraphQuery:
    """A tree pattern's atoms; absent and optional edges are edges too."""
    atoms: list[tuple[str, str, str]] = []
    for i, e in enumerate(n.edges):
        kid, p = f"{name}_{i}", e.prop.lstrip("^")
        far = e.node.value or kid
        atoms.append((far, p, name) if e.prop.startswith("^") else (name, p, far))
        atoms += as_query(e.node, kid).atoms
    return GraphQuery(tuple(atoms))


def why_not(q: GraphQuery) -> str | None:
    """Why a query is no shape: it has a property variable, computes with several values, compares counts, or its variables
    form a cycle (or fall apart); None if it is a tree of constant properties."""
    if any(p.startswith("?") for _, p, _ in q.atoms):
        return "property variable"
    if any(len(set(x)) > 1 for x in q.computed):
        return "arithmetic"
    if q.counted:
        return "counting"
    root: dict[str, str] = {}

    def find(x: str) -> str:
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for s, _, o in q.atoms:
        if s.startswith("?") and o.startswith("?"):
            a, b = find(s), find(o)
            if a == b:
                return "cycle"
            root[a] = b
    variables = {x for s, _, o in q.atoms for x in (s, o) if x.startswith("?")}
    return "not connected" if len({find(x) for x in variables}) > 1 else None


def _solutions(g: TripleGraph, n: PatternNode, engine: Engine, name: str, roots: DataFrame | None = None) -> tuple[DataFrame, list[tuple[str, str, str]]]:
    """Rows of variable bindings (one column per node) and the triples (subject column, property, object column)."""
    rows, atoms = roots, []
    if rows is None:
        known = PatternNode(tuple(e for e in n.edges if e.mode == "required"), n.value, n.test, n.classes)
        rows = engine.resolve(pattern_to_shape(known)).select(F.col("v").alias(name))
    for i, e in enumerate(n.edges):
        prop, inverse, kid = e.prop.lstrip("^"), e.prop.startswith("^"), f"{name}_{i}"
        t = g.prop(prop).select(F.col("o" if inverse else "s").alias(name), F.col("s" if inverse else "o").alias(kid))
        own = PatternNode((), e.node.value, e.node.test, e.node.classes)
        good = engine.conform(pattern_to_shape(own), t.select(F.col(kid).alias("v")).distinct()).select(F.col("v").alias(kid)) if own != PatternNode() else None
        step = t if good is None else t.join(good, kid, "left_semi").select(name, kid)
        below, more = _solutions(g, e.node, engine, kid, step) if e.node.edges else (step, [])
        if e.mode == "absent":
            rows = rows.join(below.select(name), name, "left_anti")
            continue
        rows = rows.join(below, name, "left" if e.mode == "optional" else "inner")
        atoms += [(kid, prop, name) if inverse else (name, prop, kid), *more]
    return rows, atoms


def bindings(g: TripleGraph, pattern: PatternNode) -> DataFrame:
    return _solutions(g, pattern, Engine(g), "n")[0]


def pattern_images(g: TripleGraph, pattern: PatternNode) -> DataFrame:
    """The triples that the solutions use; class targets add their type and subclass triples. Of a tree, a triple is used if
    its near end is bound and its far end fits what hangs from it, so no rows of whole solutions are made."""
    engine = Engine(g)
    found: list[DataFrame] = []

    def walk(n: PatternNode, nodes: DataFrame) -> None:
        if n.classes:
            found.append(engine.evidence(any_of(*map(class_target, n.classes)), nodes))
        for e in n.edges:
            if e.mode == "absent":
                continue
            prop, inverse = e.prop.lstrip("^"), e.prop.startswith("^")
            near, far = ("o", "s") if inverse else ("s", "o")
            used = g.raw(prop).join(nodes.select(F.col("v").alias(near)), near, "left_semi").select("s", F.lit(prop).alias("p"), "o")
            if e.node != PatternNode():
                used = cut(used, "used")
                good = engine.conform(pattern_to_shape(e.node), used.select(F.col(far).alias("v")).distinct())
                used = used.join(good.select(F.col("v").alias(far)), far, "left_semi").select("s", "p", "o")
            if e.node.edges or e.node.classes:
                used = cut(used, "used")
                walk(e.node, used.select(F.col(far).alias("v")).distinct())
            found.append(used)

    walk(pattern, cut(engine.resolve(pattern_to_shape(pattern)), "bound"))
    return reduce(DataFrame.unionAll, found).distinct()


def triple_pattern(g: TripleGraph, s: str | None = None, p: str | None = None, o: str | None = None) -> DataFrame:
    t = g.triples(None if p is None else [p])
    keep: Column = F.lit(True)
    for name, c in (("s", s), ("o", o)):
        if c is not None:
            keep = keep & (F.col(name) == c)
    return t.where(keep)
