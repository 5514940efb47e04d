"""Verdicts and evidence of shapes.

One focus level is one grouping. Every counted part of a shape (a quantifier or a pair atom, at any depth of and, or, not)
adds rows ``v, n0, n1, ...`` to one union; the sums by ``v`` decide the whole Boolean shape. A shape that no node without
such rows can satisfy is *grounded* and needs no candidate set at all; others get theirs as rows of the same union. Inner
shapes of quantifiers are grounded node sets, joined once to the ends of their path, so the plan grows with the shape's size
and not with its product. Evidence is read back for the nodes found, from set traces; evidence that carries its focus node,
and the negated pair atoms, use tagged traces.
"""

from __future__ import annotations

from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.terms import datatype, instant, is_literal, language, lexical, number
from ..plans.paths import Alt, IdPath, Inv, Path, Prop, Seq, accepts_empty, compile_path, is_step, path_text, steps_of
from ..plans.shapes import And, AtLeast, AtMost, Bottom, Closed, Compare, Disj, Eq, ForAll, HasValue, Not, Or, Shape, ShapeSchema, Test, Top, UniqueLang, all_of, conjuncts, constants, holds, is_local, negate, to_nnf
from ..sources.graph import TripleGraph, cut, local, of_kinds
from .reach import above, class_trace, ends, pairs, sources_of, sources_where, tag_ranges, trace_pairs, trace_sets, trace_tags

def grounded(s: Shape) -> bool:
    """Whether only nodes with rows of their own in the level's union can satisfy the (normal) shape."""
    match s:
        case Bottom():
            return True
        case AtLeast(n, e, x):
            return n > 0 and (not accepts_empty(e) or resolvable(x))
        case Not(Eq(e, _)):
            return not accepts_empty(e)
        case Not(Disj() | Closed() | Compare() | UniqueLang()):
            return True
        case And(a, b):
            return grounded(a) or grounded(b)
        case Or(a, b):
            return grounded(a) and grounded(b)
    return False


def resolvable(s: Shape) -> bool:
    """Whether the shape's nodes can be found without the universe."""
    match s:
        case HasValue():
            return True
        case And(a, b):
            return resolvable(a) or resolvable(b)
        case Or(a, b):
            return resolvable(a) and resolvable(b)
    return grounded(s)


def is_open(s: Shape) -> bool:
    """Whether some counted part needs the focus nodes themselves, since its path may be empty."""
    match s:
        case AtLeast(n, e, x):
            return accepts_empty(e) and n > 0 and not (n == 1 and resolvable(x))
        case AtMost(n, e, x):
            return accepts_empty(e) and not (n == 0 and resolvable(x))
        case ForAll(e, x):
            return accepts_empty(e) and not resolvable(negate(x))
        case Eq(e, _) | Disj(e, _) | Compare(e, _, _) | UniqueLang(e) | Not(Eq(e, _) | Disj(e, _) | Compare(e, _, _) | UniqueLang(e)):
            return accepts_empty(e)
        case And(a, b) | Or(a, b):
            return is_open(a) or is_open(b)
    return False


def is_own(s: Shape) -> bool:
    """Whether an atom is about triples of the focus node as their subject only."""
    match s:
        case Not(a):
            return is_own(a)
        case Eq(e, _) | Disj(e, _) | Compare(e, _, _) | UniqueLang(e):
            return isinstance(e, IdPath | Prop)
    return isinstance(s, Closed)


def first_step(e: Path) -> str | None:
    """The property that every walk along the path takes first from its focus node, if there is one."""
    match e:
        case Prop(n):
            return n
        case Seq(a, _):
            return first_step(a)
    return None


def unimplied(parts: list[Shape]) -> list[Shape]:
    """The (normal) conjuncts without those that another one implies: who takes a step of a property has a triple that breaks
    any ``closed`` without it, and a value that the property shares with itself."""
    own = {first_step(p.path) for p in parts if isinstance(p, AtLeast) and p.n} - {None}

    def implied(p: Shape) -> bool:
        match p:
            case Not(Closed(props)):
                return bool(own - props)
            case Not(Disj(Prop(q), r)):
                return q == r and q in own
        return False

    return [p for p in parts if not implied(p)]


class _Level:
    """The counted parts of one focus level and its verdict as a condition on their sums; ``kinds``: of the only nodes that
    the verdict is asked for."""

    def __init__(self, kinds: frozenset[str] | None = None) -> None:
        self.kinds = kinds
        self.ends: dict[Path, dict[Shape, str]] = {}
        self.broken: dict[Shape, str] = {}
        self.exact: set[str] = set()
        self.size = 0

    def _name(self, names: dict, key: object) -> str:
        if key not in names:
            names[key] = f"n{self.size}"
            self.size += 1
        return names[key]

    def _count(self, e: Path, x: Shape, exact: bool) -> Column:
        name = self._name(self.ends.setdefault(e, {}), x)
        if exact:
            self.exact.add(name)
        return F.col(name)

    def verdict(self, s: Shape) -> Column:
        match s:
            case And(a, b):
                return self.verdict(a) & self.verdict(b)
            case Or(a, b):
                return self.verdict(a) | self.verdict(b)
            case AtLeast(n, e, x):
                return self._count(e, x, n > 1) >= n if n else F.lit(True)
            case AtMost(n, e, x):
                return self._count(e, x, n > 0) <= n
            case ForAll(e, x):
                return F.lit(True) if isinstance(x, Top) else self._count(e, negate(x), False) == 0
            case Not(Eq() | Disj() | Closed() | Compare() | UniqueLang() as a):
                return F.col(self._name(self.broken, a)) > 0
            case Eq() | Disj() | Closed() | Compare() | UniqueLang():
                return F.col(self._name(self.broken, s)) == 0
        return holds(s, F.col("v"))


class Engine:
    def __init__(self, g: TripleGraph, schema: ShapeSchema | None = None, relax: frozenset[str] = frozenset(), extra: DataFrame | None = None):
        """``relax`` names atoms (closed, disj, compare, uniquelang) whose evidence is the wider one; ``extra`` (s, p, o) is
        added to every subgraph as far as the graph holds it."""
        self.g, self.schema, self.relax, self.extra = g, (schema or ShapeSchema()).check(), relax, extra

    # Kinds of nodes.

    def kinds_of(self, s: Shape, within: frozenset[str] | None = None) -> frozenset[str] | None:
        """How all nodes begin that satisfy the (normal) shape, as its class targets tell; None if nothing tells."""
        found = None
        match s:
            case AtLeast(n, e, HasValue(c)) if n and self.g.kinds is not None:
                up = above(self.g, e, c)
                if up is not None and up[0] == "type":
                    found = frozenset().union(*map(self.g.kinds.instances, up[2]))
            case And(a, b):
                found = self.kinds_of(b, self.kinds_of(a))
            case Or(a, b):
                sides = [self.kinds_of(a), self.kinds_of(b)]
                found = None if None in sides else sides[0] | sides[1]  # type: ignore[operator]
        return found if within is None else within if found is None else found & within

    def _about(self, kinds: frozenset[str] | None, s: Shape) -> Engine:
        """For atoms about the focus node's own triples: the engine over triples of the kinds alone."""
        if kinds is None or not is_own(s):
            return self
        return Engine(self.g.about(kinds), self.schema, self.relax)

    def _stepping(self, kinds: frozenset[str] | None, e: Path) -> Engine:
        """For the step of a property from nodes of the kinds: the engine over their triples alone."""
        return self if kinds is None or not isinstance(e, Prop) else Engine(self.g.about(kinds), self.schema, self.relax)

    # Node sets.

    def node_set(self, nodes: set[str] | list[str]) -> DataFrame:
        return local(self.g.spark, [(n,) for n in nodes], v=pa.string())

    def universe(self, *shapes: Shape) -> DataFrame:
        """Nodes of the graph and constants of the shapes; nodes elsewhere have no evidence."""
        return self.g.nodes().union(self.node_set(set().union(*map(constants, shapes)) if shapes else set())).distinct()

    def _selective(self, s: Shape) -> bool:
        """Few nodes by a constant: not through the vocabulary, whose classes hold large parts of a graph."""
        match s:
            case HasValue():
                return True
            case AtLeast(1, e, x):
                return self._selective(x) and not steps_of(e) & (self.g.vocabulary | {"type"})
            case And():
                return any(map(self._selective, conjuncts(s)))
            case Or(a, b):
                return self._selective(a) and self._selective(b)
        return False

    def resolve(self, target: Shape) -> DataFrame:
        """The nodes of the graph that satisfy a shape (column v, distinct)."""
        s = all_of(*unimplied(conjuncts(to_nnf(target, self.schema))))
        match s:
            case HasValue(c):
                return self.node_set([c])
            case Bottom():
                return self.node_set([])
            case Or(a, b) if not grounded(s) or is_open(s):
                return self.resolve(a).union(self.resolve(b)).distinct()
            case AtLeast(1, e, x) if resolvable(x) and not (is_step(e) and is_local(x)):
                return sources_of(self.g, e, x.node if isinstance(x, HasValue) else self.resolve(x)).distinct()
        parts = conjuncts(s)
        few = [p for p in parts if self._selective(p)] if len(parts) > 1 else []
        if few:
            return self.conform(all_of(*(p for p in parts if p is not few[0])), self.resolve(few[0]), True)
        if is_open(s):
            shut = [p for p in parts if not is_open(p)]
            if not any(map(grounded, shut)):
                return self.conform(s, cut(self.universe(s), "universe"), stored=True)
            return self.conform(all_of(*filter(is_open, parts)), self.resolve(all_of(*shut)))
        if not grounded(s):
            return self.conform(s, self.universe(s))
        level = _Level(self.kinds_of(s))
        verdict = level.verdict(s)
        return self._sums(level, None, False).where(verdict).select("v")

    # Verdicts.

    def conform(self, s: Shape, v: DataFrame, small: bool = False, stored: bool = False, kinds: frozenset[str] | None = None) -> DataFrame:
        """The nodes of v (distinct) that satisfy the shape. ``small``: paths start at v instead of being read whole;
        ``stored``: v is cheap to read more than once; ``kinds``: of the nodes of v."""
        s = to_nnf(s, self.schema)
        level = _Level(self.kinds_of(s, kinds))
        verdict = level.verdict(s)
        if not level.size:
            return v.where(verdict)
        return self._judged(level, v, small, stored, grounded(s)).where(verdict).select("v")

    def _judged(self, level: _Level, v: DataFrame, small: bool, stored: bool, bound: bool) -> DataFrame:
        """Sums for the nodes of v; those without rows are there unless only grounded nodes count (``bound``)."""
        paths = [*level.ends, *(getattr(a, "path", None) for a in level.broken)]
        uses = sum(small or accepts_empty(e) for e in paths) + (not (small and bound))
        if uses > 1 and not stored:
            v = cut(v, "focus")
        return self._sums(level, v, small, small and bound)

    def _sums(self, level: _Level, v: DataFrame | None, small: bool, bound: bool = False) -> DataFrame:
        """v and the sum of every counted part; only nodes of v if given (rows of ``bound`` levels are of v already)."""
        names = [f"n{i}" for i in range(level.size)]
        rows: list[DataFrame] = []

        def add(df: DataFrame, marks: dict[str, Column], focus: int = 0) -> None:
            if level.kinds is not None:
                df = df.where(of_kinds(F.col("v"), level.kinds))
            rows.append(df.select("v", *(marks.get(n, F.lit(0)).alias(n) for n in names), F.lit(focus).alias("focus")))

        for e, wanted in level.ends.items():
            near = {x: n for x, n in wanted.items() if is_local(x) and (is_step(e) or small or accepts_empty(e) or n in level.exact) and not (isinstance(x, HasValue) and n not in level.exact and not is_step(e))}
            if near:
                marks = {n: holds(x, F.col("x")).cast("int") for x, n in near.items()}
                found = self._stepping(level.kinds, e)._pairs(e, v, small, bool(level.exact & set(near.values())))
                add(found.where(reduce(lambda a, b: a | b, (holds(x, F.col("x")) for x in near))), marks)
            for x, n in wanted.items():
                if x not in near:
                    add(self._good(e, x, v, small, n in level.exact, level.kinds), {n: F.lit(1)})
        for a, n in level.broken.items():
            add(self._about(level.kinds, a)._violations(a, v if small or accepts_empty(getattr(a, "path", None)) else None).select("v"), {n: F.lit(1)})
        if v is not None and not bound:
            add(v, {}, 1)
        one = len(rows) == 1 and (v is None or bound)
        sums = [F.sum(n).alias(n) for n in names]
        if one or v is None or bound:
            return reduce(DataFrame.unionAll, rows).groupBy("v").agg(*sums)
        return reduce(DataFrame.unionAll, rows).groupBy("v").agg(*sums, F.max("focus").alias("focus")).where("focus = 1")

    def _pairs(self, e: Path, v: DataFrame | None, small: bool, exact: bool = True) -> DataFrame:
        """v, x of a path; from v only if it is small or the path may be empty. Rows may repeat unless ``exact``."""
        if is_step(e):
            turned = isinstance(e, Inv)
            name = e.path.name if turned else e.name  # type: ignore[union-attr]
            t = (self.g.prop(name) if exact else self.g.raw(name)).select(F.col("o" if turned else "s").alias("v"), F.col("s" if turned else "o").alias("x"))
            return t.join(v, "v", "left_semi") if small and v is not None else t
        return pairs(self.g, e, v if small or accepts_empty(e) else None)

    def _good(self, e: Path, x: Shape, v: DataFrame | None, small: bool, exact: bool, kinds: frozenset[str] | None = None) -> DataFrame:
        """Pairs of the path whose ends satisfy the shape x: by the shape's nodes, by those of its negation, or, if neither
        can be found from the graph alone, by judging the ends."""
        if not exact and isinstance(x, HasValue):
            found = sources_of(self.g, e, x.node, kinds)
            return found.join(v, "v", "left_semi") if small and v is not None else found
        if not small and not exact and is_local(x):
            return sources_where(self._stepping(kinds, e).g, e, lambda o: holds(x, o))
        if not small and resolvable(x):
            good = self.resolve(x)
            if not exact:
                return sources_of(self.g, e, good)
            return self._pairs(e, v, small).join(good.withColumnRenamed("v", "x"), "x", "left_semi")
        found = self._pairs(e, v, small, exact)
        if not small and resolvable(negate(x)):
            return found.join(self.resolve(negate(x)).withColumnRenamed("v", "x"), "x", "left_anti")
        if not is_step(e) or small:
            found = cut(found, "pairs")
        good = self.conform(x, found.select(F.col("x").alias("v")).distinct(), small)
        return found.join(good.withColumnRenamed("v", "x"), "x", "left_semi").select("v", "x")

    def _values(self, p: str, v: DataFrame | None) -> DataFrame:
        t = self.g.prop(p).select(F.col("s").alias("v"), F.col("o").alias("y"))
        return t if v is None else t.join(v, "v", "left_semi")

    def _both(self, a: Eq | Disj, v: DataFrame | None) -> DataFrame:
        """v, x, left, right: whether a pair is one of the path and one of the property."""
        left = pairs(self.g, a.path, v).select("v", "x", F.lit(1).alias("left"), F.lit(0).alias("right"))
        right = self._values(a.prop, v).select("v", F.col("y").alias("x"), F.lit(0), F.lit(1))
        return left.unionAll(right).groupBy("v", "x").agg(F.max("left").alias("left"), F.max("right").alias("right"))

    def _violations(self, a: Shape, v: DataFrame | None) -> DataFrame:
        """Rows with column v for nodes that break the atom."""
        match a:
            case Eq():
                return self._both(a, v).where("left <> right")
            case Disj():
                return self._both(a, v).where("left = right")
            case Closed(props):
                t = self.g.triples(set(self.g.parts) - set(props), exact=False).select(F.col("s").alias("v"))
                return t if v is None else t.join(v, "v", "left_semi")
            case Compare():
                return self._unordered(a, v)
            case UniqueLang(e):
                shared = self._clashes(e)[2] if v is None and not is_own(a) else None
                if shared is not None:
                    return shared
                return self._tags(e, v).groupBy("v", "tag").agg(F.count_distinct("x").alias("n")).where("n > 1")
        raise TypeError(f"no atom: {a}")

    def _unordered(self, a: Compare, v: DataFrame | None) -> DataFrame:
        """Nodes with two values out of order, from extremes instead of pairs: all ends and values must be of one comparable
        kind, and then the extremes of both sides decide."""
        x = pairs(self.g, a.path, v).select("v", F.col("x").alias("t"), F.lit(True).alias("own"))
        rows = x.unionAll(self._values(a.prop, v).select("v", F.col("y").alias("t"), F.lit(False).alias("own")))
        n, t = number(F.col("t")), instant(F.col("t"))
        real = n.isNotNull() & ~F.isnan(n)
        word = datatype(F.col("t")) == "string"
        rows = rows.select("v", "own", F.when(real, n).alias("n"), F.when(~real, t).alias("m"), F.when(~real & t.isNull() & word, lexical(F.col("t"))).alias("w"))
        most, least = (F.max, F.min) if a.relation in ("<", "<=") else (F.min, F.max)
        sides = [("own", F.col("own"), most), ("val", ~F.col("own"), least)]
        sums = [F.count(F.when(of, 1)).alias(k) for k, of, _ in sides]
        sums += [f(F.when(of, F.col(c))).alias(f"{k}_{c}") for k, of, f in sides for c in "nmw"]
        sums += [F.count(c).alias(f"all_{c}") for c in "nmw"]
        whole = F.col("own") + F.col("val")
        order = {"<": Column.__lt__, "<=": Column.__le__, ">": Column.__gt__, ">=": Column.__ge__}[a.relation]
        fine = reduce(lambda p, q: p | q, [(F.col(f"all_{c}") == whole) & order(F.col(f"own_{c}"), F.col(f"val_{c}")) for c in "nmw"])
        return rows.groupBy("v").agg(*sums).where((F.col("own") > 0) & (F.col("val") > 0) & ~F.coalesce(fine, F.lit(False)))

    def _bad_comparisons(self, a: Compare, v: DataFrame) -> DataFrame:
        return pairs(self.g, a.path, v).join(self._values(a.prop, v), "v").where(~a.holds(F.col("x"), F.col("y")))

    def _clashes(self, e: Path) -> tuple:
        """The automaton and ranges of ``tag_ranges``, and v, tag of two ends or more; Nones for paths that have no ranges."""
        found = tag_ranges(self.g, e, language)
        return (None, None, None) if found is None else (*found, found[1][0].where("lo <> hi").select(F.col("x").alias("v"), "tag"))

    def _tags(self, e: Path, v: DataFrame | None) -> DataFrame:
        return pairs(self.g, e, v).where(is_literal(F.col("x"))).withColumn("tag", language(F.col("x"))).where("tag <> ''")

    def _shared_tags(self, e: Path, v: DataFrame) -> DataFrame:
        """v, x: ends that share their language tag with another end."""
        tagged = self._tags(e, v)
        shared = tagged.groupBy("v", "tag").agg(F.count_distinct("x").alias("n")).where("n > 1")
        return tagged.join(shared, ["v", "tag"], "left_semi").select("v", "x")

    # Evidence.

    def evidence(self, s: Shape, v: DataFrame, tagged: bool = False, small: bool = False) -> DataFrame:
        """Triples that show why those nodes of v that satisfy the shape do: s, p, o (v, s, p, o if tagged)."""
        nnf = to_nnf(s, self.schema)
        return self._evidence(nnf, cut(self.conform(nnf, v, small), "nodes"), tagged, small).distinct()

    def _empty(self, tagged: bool) -> DataFrame:
        return local(self.g.spark, [], **dict.fromkeys("vspo" if tagged else "spo", pa.string()))

    def _evidence(self, s: Shape, v: DataFrame, tagged: bool, small: bool = False, kinds: frozenset[str] | None = None) -> DataFrame:
        """Of nodes that all satisfy the (normal) shape; v is stored. A path whose triples are all shown already is not
        traced again for the other parts of the conjunction."""
        kinds = self.kinds_of(s, kinds)
        if tagged:
            return reduce(DataFrame.unionAll, [self._part(p, v, True, small, kinds) for p in conjuncts(s)])
        found, parts = [], list(dict.fromkeys(conjuncts(s)))
        whole = {p.path for p in parts if isinstance(p, ForAll) or (isinstance(p, AtLeast) and isinstance(p.shape, Top))}
        stars: dict[str, list[Shape]] = {}
        for p in parts:
            if isinstance(p, AtLeast | AtMost | ForAll):
                x = negate(p.shape, self.schema) if isinstance(p, AtMost) else p.shape
                shown = Top() if p.path in whole else x
                if isinstance(p.path, Prop) and is_local(shown) and (is_local(x) or p.path in whole):
                    stars.setdefault(p.path.name, []).append(shown)
                    if not is_local(x):
                        found.append(self._inner(p.path, x, v, small))
                    continue
                if isinstance(x, Bottom):
                    continue
            found.append(self._part(p, v, False, small, kinds))
        if stars:
            g = self.g if kinds is None else self.g.about(kinds)
            rows = [g.raw(p).select("s", F.lit(p).alias("p"), "o").where(reduce(lambda a, b: a | b, (holds(x, F.col("o")) for x in xs))) for p, xs in stars.items()]
            found.append(reduce(DataFrame.unionAll, rows).join(v.withColumnRenamed("v", "s"), "s", "left_semi"))
        return reduce(DataFrame.unionAll, found) if found else self._empty(False)

    def _part(self, s: Shape, v: DataFrame, tagged: bool, small: bool, kinds: frozenset[str] | None = None) -> DataFrame:
        if kinds is not None and is_own(s):
            return self._about(kinds, s)._part(s, v, tagged, small)
        g = self.g
        drop = (lambda df: df) if tagged else (lambda df: df.select("s", "p", "o"))
        match s:
            case Or(a, b):
                sides = [self._evidence(x, cut(self.conform(x, v, small, True, kinds), "side"), tagged, small, kinds) for x in (a, b)]
                return sides[0].unionAll(sides[1])
            case And():
                return self._evidence(s, v, tagged, small, kinds)
            case AtLeast(_, e, x) | ForAll(e, x):
                return self._along(e, x, v, tagged, small, kinds)
            case AtMost(_, e, x):
                return self._along(e, negate(x, self.schema), v, tagged, small, kinds)
            case Eq(IdPath(), p):
                return drop(self._own(p, v).where("s = o"))
            case Eq(e, p) if not tagged:
                whole = Alt(e, Prop(p))
                return trace_sets(g, whole, v, ends(g, whole, v))
            case Eq(e, p):
                return trace_pairs(g, Alt(e, Prop(p)), pairs(g, Alt(e, Prop(p)), v))
            case Not(Eq(IdPath(), p)):
                return drop(self._own(p, v).where("s <> o"))
            case Not(Eq(e, p) as a):
                return self._traced(e, p, cut(self._both(a, v).where("left <> right"), "sides"), v, tagged)
            case Not(Disj(IdPath(), p)):
                return drop(self._own(p, v).where("s = o"))
            case Not(Disj(Prop(q), p)) if q == p:
                return drop(self._own(p, v))
            case Not(Disj(e, p) as a):
                return self._traced(e, p, cut(self._both(a, v).where("left = right"), "sides"), v, tagged)
            case Not(Compare() as a):
                bad = cut(self._bad_comparisons(a, v), "sides")
                own = self._own(a.prop, v).join(bad.select("v", F.col("y").alias("o")).distinct(), ["v", "o"], "left_semi")
                return drop(trace_pairs(g, a.path, bad.select("v", "x").distinct()).unionAll(own.select("v", "s", "p", "o")))
            case Not(UniqueLang(e)) if not tagged and not small and not accepts_empty(e) and not is_step(e) and compile_path(e).order() is not None:
                a, ranges, shared = self._clashes(e)
                return trace_tags(g, a, ranges, cut(shared.join(v, "v", "left_semi").select(F.col("v").alias("x"), "tag"), "sides"))
            case Not(UniqueLang(e)):
                return drop(trace_pairs(g, e, cut(self._shared_tags(e, v), "sides")))
            case Not(Closed(props)):
                return drop(self._all(set(g.parts) - set(props), v))
            case Closed() if "closed" in self.relax:
                return drop(self._all(set(g.parts), v))
            case Disj(e, p) | Compare(e, _, p) if type(s).__name__.lower() in self.relax and not isinstance(e, IdPath):
                return drop(trace_pairs(g, e, pairs(g, e, v)).unionAll(self._own(p, v)))
            case UniqueLang(e) if "uniquelang" in self.relax:
                return drop(trace_pairs(g, e, pairs(g, e, v)))
        return self._empty(tagged)

    def _traced(self, e: Path, p: str, sides: DataFrame, v: DataFrame, tagged: bool) -> DataFrame:
        """Paths to the ends of ``sides`` that are ends of the path, and the property's triples to those that are its values."""
        paths = trace_pairs(self.g, e, sides.where("left = 1").select("v", "x"))
        own = self._own(p, v).join(sides.where("right = 1").select("v", F.col("x").alias("o")), ["v", "o"], "left_semi").select("v", "s", "p", "o")
        both = paths.unionAll(own)
        return both if tagged else both.select("s", "p", "o")

    def _own(self, p: str, v: DataFrame) -> DataFrame:
        return self._all({p}, v)

    def _all(self, props: set[str], v: DataFrame) -> DataFrame:
        t = self.g.triples(sorted(props), exact=False)  # evidence ends in a set
        return t.join(v.select(F.col("v").alias("s")), "s", "left_semi").select(F.col("s").alias("v"), "s", "p", "o")

    def _reached(self, e: Path, x: Shape, v: DataFrame, small: bool) -> DataFrame:
        """Ends of the path that satisfy x; written once if x has evidence of its own."""
        far = ends(self.g, e, v)
        if is_local(x):
            return far.where(holds(x, F.col("v")))
        good = far.join(self.resolve(x), "v", "left_semi") if not small and resolvable(x) else self.conform(x, far, small)
        return cut(good, "ends")

    def _inner(self, e: Path, x: Shape, v: DataFrame, small: bool) -> DataFrame:
        return self._evidence(x, self._reached(e, x, v, small), False, small)

    def _along(self, e: Path, x: Shape, v: DataFrame, tagged: bool, small: bool, kinds: frozenset[str] | None = None) -> DataFrame:
        """Paths to the ends that satisfy x, and the evidence of those ends; ``kinds``: of the nodes of v."""
        g = self.g
        if is_local(x) and isinstance(e, Prop) and kinds is not None:
            return self._stepping(kinds, e)._along(e, x, v, tagged, small)
        if not tagged and isinstance(e, Prop) and is_local(x):
            return g.raw(e.name).where(holds(x, F.col("o"))).join(v.select(F.col("v").alias("s")), "s", "left_semi").select("s", F.lit(e.name).alias("p"), "o")
        if tagged:
            found = pairs(g, e, v)
            if is_local(x):
                return trace_pairs(g, e, found.where(holds(x, F.col("x"))))
            found = cut(found, "pairs")
            good = cut(found.join(self.conform(x, found.select(F.col("x").alias("v")).distinct(), small).withColumnRenamed("v", "x"), "x", "left_semi").select("v", "x"), "ends")
            inner = self._evidence(x, cut(good.select(F.col("x").alias("v")).distinct(), "ends"), True, small)
            carried = good.join(inner.withColumnRenamed("v", "x"), "x").select("v", "s", "p", "o")
            return trace_pairs(g, e, good).unionAll(carried)
        if isinstance(x, HasValue):
            direct = class_trace(g, e, v, x.node, kinds)
            if direct is not None:
                return direct
        good = self._reached(e, x, v, small)
        traced = trace_sets(g, e, v, good)
        return traced if is_local(x) else traced.unionAll(self._evidence(x, good, False, small))

    # Requests.

    def evidence_of(self, s: Shape, node: str) -> DataFrame:
        return self.evidence(s, self.node_set([node]), small=True)

    def select_nodes(self, *shapes: Shape) -> DataFrame:
        found = [self.resolve(s) for s in shapes]
        return reduce(DataFrame.union, found).distinct() if len(found) > 1 else found[0]

    def subgraph(self, *shapes: Shape) -> DataFrame:
        """The union of evidence over all nodes and request shapes."""
        found = [] if self.extra is None else [self.extra.select("s", "p", "o").join(self.g.triples(), ["s", "p", "o"], "left_semi")]
        for s in shapes:
            nnf = to_nnf(s, self.schema)
            few = any(map(self._selective, conjuncts(nnf)))
            v = cut(self.resolve(nnf), "nodes")
            apart = self._own_apart(nnf, v, few) if len(shapes) == 1 and not found else None
            if apart is not None:
                return apart
            found.append(self._evidence(nnf, v, False, few))
        return reduce(DataFrame.unionAll, found, self._empty(False)).distinct()

    def _own_apart(self, s: Shape, v: DataFrame, small: bool) -> DataFrame | None:
        """The distinct evidence of a conjunction with a ``not closed``, whose triples are the nodes' own and most of all: they
        are dealt by subject once, to find the nodes' and to drop repeated rows, where no other part shows their properties
        at other subjects; else None."""
        parts, kinds = list(dict.fromkeys(conjuncts(s))), self.kinds_of(s)
        wide = [p for p in parts if isinstance(p, Not) and isinstance(p.shape, Closed)]
        if len(wide) != 1 or kinds is None:
            return None
        shown = set(self.g.parts) - wide[0].shape.props
        found = []
        for p in parts:
            up = above(self.g, p.path, p.shape.node) if isinstance(p, AtLeast) and isinstance(p.shape, HasValue) else None
            if up is not None:
                links = class_trace(self.g, p.path, v, p.shape.node, kinds)
                if links is None or up[1] in shown and self._subjects(up[1]) & kinds:
                    return None
                found.append(links.where(F.col("p") != up[0]) if up[0] in shown else links)
            elif p not in wide:
                used = self._uses(p)
                if used is None or used & shown and not (isinstance(p, Not) and is_own(p) and used <= shown):
                    return None
                if not used & shown:
                    found.append(self._part(p, v, False, small, kinds))
        own = self.g.about(kinds).triples(shown, exact=False).join(v.select(F.col("v").alias("s")), "s", "left_semi").select("s", "p", "o").distinct()
        return own.unionAll(reduce(DataFrame.unionAll, found).distinct()) if found else own

    def _subjects(self, p: str) -> frozenset[str]:
        return self.g.kinds.subjects.get(p, frozenset()) if self.g.kinds else frozenset()

    def _uses(self, s: Shape) -> set[str] | None:
        """The properties of the (normal) shape's evidence; None if they are not known beforehand."""
        match s:
            case And(a, b) | Or(a, b):
                sides = [self._uses(a), self._uses(b)]
                return None if None in sides else sides[0] | sides[1]  # type: ignore[operator]
            case AtLeast(_, e, x) | AtMost(_, e, x) | ForAll(e, x):
                inner = self._uses(negate(x, self.schema) if isinstance(s, AtMost) else x)
                return None if inner is None else inner | steps_of(e)
            case Closed():
                return None
            case Not(a):
                return self._uses(a)
            case Eq(e, p) | Disj(e, p) | Compare(e, _, p):
                return steps_of(e) | {p}
            case UniqueLang(e):
                return set(steps_of(e))
        return set()

    def schema_subgraph(self) -> DataFrame:
        return self.subgraph(*self.schema.requests())

    # Validation.

    def report(self, detail: bool = False) -> DataFrame:
        """shape, focus, component, path, value, message of every target node that breaks its shape, or, with detail, each of
        its failing conjuncts; a definition is one grouping of target and shape together."""
        found = []
        for d in self.schema.defs:
            nnf, target = to_nnf(d.shape, self.schema), to_nnf(d.target, self.schema)
            if not detail:
                bad = self.resolve(all_of(target, negate(nnf)))
                found.append(self._reported(bad, d.name, F.lit("shape"), F.lit(""), F.lit("")))
                continue
            parts = conjuncts(nnf)
            level = _Level()
            fails = [~level.verdict(p) for p in parts]
            v = self.resolve(target)
            judged = self._judged(level, v, False, False, False) if level.size else v
            rows = judged.select("v", F.explode(F.array_compact(F.array(*(F.when(c, F.struct(F.lit(type(p).__name__).alias("component"), F.lit(path_text(p.path) if hasattr(p, "path") else "").alias("path"), F.lit(str(i)).alias("value"))) for i, (p, c) in enumerate(zip(parts, fails, strict=True)))))).alias("at"))
            found.append(self._reported(rows, d.name, F.col("at.component"), F.col("at.path"), F.col("at.value")))
        empty = local(self.g.spark, [], **dict.fromkeys(("shape", "focus", "component", "path", "value", "message"), pa.string()))
        return reduce(DataFrame.unionAll, found, empty)

    @staticmethod
    def _reported(bad: DataFrame, name: str, component: Column, where: Column, value: Column) -> DataFrame:
        return bad.select(F.lit(name).alias("shape"), F.col("v").alias("focus"), component.alias("component"), where.alias("path"), value.alias("value"), F.lit("does not conform").alias("message"))

    def conforms(self) -> bool:
        return self.report().isEmpty()

    def judged(self, target: Shape, s: Shape, v: DataFrame | None = None) -> DataFrame:
        """v, ok of every target node: one grouping over the rows of target and shape."""
        nnf = to_nnf(s, self.schema)
        level = _Level()
        verdict = level.verdict(nnf)
        stored = v is not None
        v = self.resolve(target) if v is None else v
        return (self._judged(level, v, False, stored, False) if level.size else v).select("v", verdict.alias("ok"))

    def validate_and_extract(self) -> tuple[DataFrame, DataFrame]:
        """Report and schema subgraph from the same verdicts, written once. Star shapes take verdict and evidence rows from
        one window; other shapes trace the evidence of the nodes that conform."""
        from .star import is_star, star_window

        reports, found = [], []
        for d in self.schema.defs:
            nnf, target = to_nnf(d.shape, self.schema), to_nnf(d.target, self.schema)
            if is_star(nnf):
                rows = cut(star_window(self.g, nnf, self.resolve(target)), "marked")
                found.append(rows.where("ok and evidence").select("s", "p", "o"))
                bad, good = rows.where("not ok").select("v").distinct(), rows.where("ok").select("v").distinct()
            else:
                rows = cut(self.judged(target, nnf), "verdict")
                bad, good = rows.where("not ok").select("v"), rows.where("ok").select("v")
                found.append(self._evidence(nnf, good, False))
            reports.append(self._reported(bad, d.name, F.lit("shape"), F.lit(""), F.lit("")))
            found.append(self._evidence(target, good, False))
        report = reduce(DataFrame.unionAll, reports) if reports else self.report()
        return report, reduce(DataFrame.unionAll, found, self._empty(False)).distinct()


def summarise(report: DataFrame) -> DataFrame:
    return report.cube("shape", "component").agg(F.count("*").alias("violations"))
