"""Translation of shapes to one Spark SQL text (views ``triples`` and ``universe``).

Each sub-shape and path becomes a common table expression named by its structure, so equal parts are written once.
Closures of stars are tables that the caller supplies, since SQL recursion does not end on cycles.

Relations may hold a row more than once where that cannot multiply; what counts or is returned is made distinct. Steps that
meet in a table's row (``Rows``) are read from that row. A sieve holds one bit per hash of a relation's keys: rows that fail
it have no partner, so they are dropped before they would be shuffled, and the join itself still decides.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.reach import pairs
from ..sources.graph import Rows, TripleGraph, cut, local
from .paths import Alt, IdPath, Inv, Opt, Path, Prop, Seq, Star, accepts_empty, is_step, path_text, push_inverse, steps_of
from ..functions.terms import NUMERIC, TEMPORAL
from .shapes import And, AtLeast, AtMost, Bottom, Closed, Compare, Disj, Eq, ForAll, HasValue, Not, Or, Shape, ShapeSchema, Test, Top, UniqueLang, conjuncts, negate, to_nnf


#: Bits of a sieve, and the parts of a text that are written once when they are used again or when rows were sieved.
BITS = 1 << 26
WRITTEN = re.compile(r"^(nodes|carried|common|sifted)_")


@dataclass(frozen=True)
class InRow(Path):
    """Two steps that meet in the node of a table's row."""

    first: Path
    second: Path


def leaves(e: Path) -> frozenset[str]:
    return leaves(e.first) | leaves(e.second) if isinstance(e, InRow | Seq | Alt) else leaves(e.path) if isinstance(e, Opt) else steps_of(e)


class Translator:
    def __init__(self, closure: Callable[[Path], str] | None = None, rows: Rows | None = None):
        self.ctes: dict[str, str] = {}
        self.closure, self.rows = closure, rows
        self.narrow: set[str] = set()

    def _named(self, kind: str, key: object, body: str) -> str:
        name = f"{kind}_{hashlib.md5(repr(key).encode()).hexdigest()[:10]}"
        self.ctes.setdefault(name, body)
        return name

    @staticmethod
    def _quote(text: str) -> str:
        return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"

    # Steps that meet in a row, and what is known of sizes.

    def _meets(self, a: Path, b: Path) -> bool:
        """Whether the step's head and the next one's tail are the node of one row, which tells one of the other two ends: then
        all rows of that node agree in it, so a row alone holds each pair."""
        r = self.rows
        if r is None or not (is_step(a) and is_step(b)):
            return False
        (p, p_in), (q, q_in) = ((x.path.name, True) if isinstance(x, Inv) else (x.name, False) for x in (a, b))
        return p in (r.out if p_in else r.into) and q in (r.into if q_in else r.out) and bool({p, q} & r.told)

    def plan(self, e: Path) -> Path:
        """The same relation, inverses on properties only and steps that meet in a row as one."""
        return self._merge(push_inverse(e))

    def _merge(self, e: Path) -> Path:
        match e:
            case Seq():
                steps: list[Path] = []

                def walk(x: Path) -> None:
                    if isinstance(x, Seq):
                        walk(x.first)
                        walk(x.second)
                    elif steps and self._meets(steps[-1], x):
                        steps[-1] = InRow(steps[-1], x)
                    else:
                        steps.append(self._merge(x))

                walk(e)
                return reduce(lambda rest, x: Seq(x, rest), reversed(steps[:-1]), steps[-1])
            case Alt(a, b):
                return Alt(self._merge(a), self._merge(b))
            case Opt(a):
                return Opt(self._merge(a))
        return e

    def _single(self, e: Path, back: bool = False) -> bool:
        """Whether nodes have one end of the path (``back``: ends have one node), by the mapping's own account; it decides on
        what is worth a shuffle, never on results."""
        match e:
            case Seq(a, b) | InRow(a, b):
                return self._single(a, back) and self._single(b, back)
        turned = Inv(e) if back and isinstance(e, Prop) else e.path if back and isinstance(e, Inv) else e
        return self.rows is not None and (path_text(turned) in self.rows.single)

    def _bounded(self, a: Path, b: Path) -> bool:
        return self._single(b) or self._single(a, True)

    def _large(self, e: Path) -> bool:
        return self.rows is not None and bool(leaves(e) & (self.rows.out | self.rows.into | {"type"}))

    def _on(self, a: Path) -> str:
        """The join of a path's rows with the next one's, which starts at nodes of one kind if the last step ends there."""
        prefix = self.rows.ends.get(a.second.name) if self.rows and isinstance(a, InRow) and isinstance(a.second, Prop) else None
        return f"x.h = y.t AND startswith(y.t, {self._quote(prefix)})" if prefix else "x.h = y.t"

    def _tidy(self, e: Path) -> bool:
        """Whether a triple of the path is not repeated for many ends."""
        match e:
            case Seq(a, b):
                return self._bounded(a, b) and self._tidy(a) and self._tidy(b)
            case Star():
                return self._single(e)
        return isinstance(e, Prop | Inv | InRow)

    def _found(self, e: Path, nodes: str) -> str:
        """The path's triples, those of narrow sets of nodes sieved if there are many."""
        return self.sifted(self.path(e), ["t"], nodes, ["v"]) if nodes in self.narrow and self._large(e) else self.path(e)

    def sieve(self, relation: str, *columns: str) -> str:
        key = self._key(columns)
        return self._named("sieve", (relation, columns), f"SELECT {key} DIV 64 AS k, bit_or(shiftleft(1L, CAST({key} % 64 AS int))) AS bits FROM {relation} GROUP BY {key} DIV 64")

    @staticmethod
    def _key(columns: tuple[str, ...] | list[str]) -> str:
        return f"pmod(xxhash64({', '.join(columns)}), {BITS}L)"

    def sifted(self, relation: str, columns: list[str], keys: str, names: list[str]) -> str:
        """The relation without rows that have no partner among the keys; some without one stay."""
        key = self._key([f"x.{c}" for c in columns])
        return self._named("sifted", (relation, columns, keys, names), f"SELECT /*+ BROADCAST(b) */ x.* FROM {relation} x JOIN {self.sieve(keys, *names)} b ON {key} DIV 64 = b.k WHERE getbit(b.bits, CAST({key} % 64 AS int)) = 1")

    def path(self, e: Path) -> str:
        """A relation (t, s, p, o, h): tail, one triple of a path that is not empty, head."""
        return self._path(self.plan(e))

    def moves(self, e: Path) -> str:
        """A relation (t, h) of a path's ends, without those that only the empty path joins to themselves."""
        return self._moves(self.plan(e))

    def _row(self, e: InRow) -> tuple[str, str, str, str]:
        """The outer ends of two steps that meet in a row, the struct of their triples and the condition that they are there."""
        ends = [x.path.name if isinstance(x, Inv) else x.name for x in (e.first, e.second)]
        made = [f"named_struct('s', {'node' if p in self.rows.out else p}, 'p', {self._quote(p)}, 'o', {p if p in self.rows.out else 'node'})" for p in ends]
        return ends[0], ends[1], f"array({', '.join(dict.fromkeys(made))})", " AND ".join(["known", *(f"{c} IS NOT NULL" for c in dict.fromkeys(ends))])

    def _path(self, e: Path) -> str:
        match e:
            case Prop(n):
                body = f"SELECT s AS t, s, p, o, o AS h FROM triples WHERE p = {self._quote(n)}"
            case Inv(Prop(n)):
                body = f"SELECT o AS t, s, p, o, s AS h FROM triples WHERE p = {self._quote(n)}"
            case InRow():
                t, h, made, there = self._row(e)
                body = f"SELECT t, made.s, made.p, made.o, h FROM (SELECT {t} AS t, {h} AS h, explode({made}) AS made FROM {self.rows.view} WHERE {there})"
            case Alt(a, b):
                body = f"SELECT * FROM {self._path(a)} UNION ALL SELECT * FROM {self._path(b)}"
            case Opt(a):
                return self._path(a)
            case Seq(a, b):
                x, y, union = self._path(a), self._path(b), "UNION ALL" if self._bounded(a, b) else "UNION"
                body = f"SELECT x.t, x.s, x.p, x.o, y.h FROM {x} x JOIN {self._moves(b)} y ON {self._on(a)} {union} SELECT x.t, y.s, y.p, y.o, y.h FROM {self._moves(a)} x JOIN {y} y ON {self._on(a)}"
                body += f" {union} SELECT * FROM {x}" if accepts_empty(b) else ""
                body += f" {union} SELECT * FROM {y}" if accepts_empty(a) else ""
            case Star(a):
                star, step = self._moves(e), self.path(a)
                body = f"SELECT x.t, y.s, y.p, y.o, z.h FROM {star} x JOIN {step} y ON x.h = y.t JOIN {star} z ON y.h = z.t"
            case _:
                raise TypeError(f"no path: {e}")
        return self._named("path", e, body)

    def _moves(self, e: Path) -> str:
        match e:
            case Prop(n):
                body = f"SELECT s AS t, o AS h FROM triples WHERE p = {self._quote(n)}"
            case Inv(Prop(n)):
                body = f"SELECT o AS t, s AS h FROM triples WHERE p = {self._quote(n)}"
            case InRow():
                t, h, _, there = self._row(e)
                body = f"SELECT {t} AS t, {h} AS h FROM {self.rows.view} WHERE {there}"
            case Alt(a, b):
                body = f"SELECT * FROM {self._moves(a)} UNION ALL SELECT * FROM {self._moves(b)}"
            case Opt(a):
                return self._moves(a)
            case Seq(a, b):
                x, y, union = self._moves(a), self._moves(b), "UNION ALL" if self._bounded(a, b) else "UNION"
                body = f"SELECT {'' if accepts_empty(a) or accepts_empty(b) or self._bounded(a, b) else 'DISTINCT '}x.t, y.h FROM {x} x JOIN {y} y ON {self._on(a)}"
                body += f" {union} SELECT t, h FROM {x}" if accepts_empty(b) else ""
                body += f" {union} SELECT t, h FROM {y}" if accepts_empty(a) else ""
            case Star(_):
                if self.closure is None:
                    raise ValueError("a star needs a closure table")
                return self.closure(e)
            case _:
                raise TypeError(f"no path: {e}")
        return self._named("moves", e, body)

    def ends(self, e: Path) -> str:
        if isinstance(e, IdPath):
            return self._named("ends", e, "SELECT v AS t, v AS h FROM universe")
        if not accepts_empty(e):
            return self.moves(e)
        return self._named("ends", e, f"SELECT t, h FROM {self.moves(e)} UNION SELECT v, v FROM universe")

    def among(self, x: Shape, column: str) -> str:
        """Whether the column's node satisfies the (normal) shape."""
        match x:
            case Top():
                return "true"
            case Bottom():
                return "false"
            case HasValue(c):
                return f"{column} = {self._quote(c)}"
            case Not(HasValue(c)):
                return f"{column} <> {self._quote(c)}"
        return f"{column} IN (SELECT v FROM {self.conform(x)})"

    def nested(self, e: Path, x: Shape) -> tuple[Path, Shape]:
        """``some p with some q with x`` as ``some p/q with x`` if the steps meet in a row: the same nodes and evidence."""
        while isinstance(x, AtLeast) and x.n == 1 and self._meets(e, x.path):
            e, x = Seq(e, x.path), x.shape
        return e, x

    @classmethod
    def filters(cls, s: Shape) -> bool:
        """Whether the shape is decided for given nodes, so that it needs no universe beside another shape's nodes."""
        match s:
            case And(a, b):
                return cls.filters(a) and cls.filters(b)
            case AtLeast(n, _, _):
                return n == 0
            case Not(a):
                return isinstance(a, HasValue | Test)
        return not isinstance(s, Or)

    def conform(self, s: Shape, base: str = "universe") -> str:
        """A relation (v) of the nodes that satisfy the (normal) shape; of those of ``base`` if the shape filters."""
        match s:
            case Top():
                body = f"SELECT v FROM {base}"
            case Bottom():
                body = f"SELECT v FROM {base} WHERE false"
            case HasValue(c):
                body = f"SELECT v FROM {base} WHERE v = {self._quote(c)}"
            case Test(t):
                body = f"SELECT v FROM {base} WHERE {self.test(t)}"
            case And(a, b) if self.filters(a):
                return self.conform(a, self.conform(b, base))
            case And(a, b) if self.filters(b):
                return self.conform(b, self.conform(a))
            case And(a, b):
                body = f"SELECT v FROM {self.conform(a)} LEFT SEMI JOIN {self.conform(b)} USING (v)"
            case Or(a, b):
                body = f"SELECT v FROM {self.conform(a)} UNION SELECT v FROM {self.conform(b)}"
            case AtLeast(n, e, x) if n:
                e, x = self.nested(e, x) if n == 1 else (e, x)
                ends, own = self.ends(e), self.among(x, "h")
                body = f"SELECT DISTINCT t AS v FROM {ends} WHERE {own}" if n == 1 else f"SELECT t AS v FROM {ends} WHERE {own} GROUP BY t HAVING count(DISTINCT h) >= {n}"
            case AtLeast():
                body = f"SELECT v FROM {base}"
            case AtMost(n, e, x):
                body = f"SELECT v FROM {base} LEFT ANTI JOIN (SELECT t AS v FROM {self.ends(e)} WHERE {self.among(x, 'h')} GROUP BY t HAVING count({'DISTINCT h' if n else '*'}) > {n}) USING (v)"
            case ForAll(e, x):
                body = f"SELECT v FROM {base} LEFT ANTI JOIN (SELECT t AS v FROM {self.ends(e)} LEFT ANTI JOIN {self.conform(x)} x ON h = x.v) USING (v)"
            case Eq() | Disj() | Closed() | Compare() | UniqueLang():
                body = f"SELECT v FROM {base} LEFT ANTI JOIN ({self.broken(s)}) USING (v)"
            case Not(HasValue() | Test() as a):
                body = f"SELECT v FROM {base} LEFT ANTI JOIN {self.conform(a)} USING (v)"
            case Not(a):
                body = f"SELECT DISTINCT v FROM ({self.broken(a)})"
            case _:
                raise TypeError(f"not translated: {s}")
        return self._named("nodes", (s, base), body)

    def broken(self, a: Shape) -> str:
        match a:
            case Eq(e, p):
                return f"SELECT v FROM {self.sides(a, False)}"
            case Disj(e, p):
                if carried := self.common(a):
                    return f"SELECT t AS v FROM {carried}"
                return f"SELECT t AS v FROM (SELECT * FROM {self.ends(e)} INTERSECT SELECT * FROM {self.ends(Prop(p))})"
            case Closed(props):
                return f"SELECT s AS v FROM triples WHERE p NOT IN ({', '.join(map(self._quote, sorted(props))) or 'NULL'})"
            case Compare():
                return f"SELECT v FROM {self.unordered(a)}"
            case UniqueLang(e):
                return f"SELECT v FROM {self.clashes(e)}"
        raise TypeError(f"not translated: {a}")

    def sides(self, a: Eq | Disj, common: bool) -> str:
        """A relation (v, h, far, near): pairs of the path and of the property that both have, or that one lacks."""
        x, y = self.ends(a.path), self.ends(Prop(a.prop))
        body = f"SELECT t AS v, h, max(far) AS far, max(near) AS near FROM (SELECT t, h, 1 AS far, 0 AS near FROM {x} UNION ALL SELECT t, h, 0, 1 FROM {y}) GROUP BY t, h HAVING max(far) {'=' if common else '<>'} max(near)"
        return self._named("sides", (a, common), body)

    def common(self, a: Disj) -> str | None:
        """A relation (t, m, h) of the pairs that the path and the property share, with the node after the path's first step.
        The property's values are carried over that step, so the rest of the path is asked for given pairs; None if a node
        after the first step can have many before it, since each of them would carry its values."""
        e = self.plan(a.path) if not isinstance(a.path, IdPath) else a.path
        if not (isinstance(e, Seq) and is_step(e.first) and self._single(e.first, True) and not accepts_empty(e.second)):
            return None
        carried = self._named("carried", a, f"SELECT x.t, x.h AS m, y.h FROM {self._moves(e.first)} x JOIN {self.ends(Prop(a.prop))} y ON x.t = y.t")
        rest = self.sifted(self._moves(e.second), ["t", "h"], carried, ["m", "h"])
        return self._named("common", a, f"SELECT DISTINCT c.t, c.m, c.h FROM {carried} c LEFT SEMI JOIN {rest} r ON c.m = r.t AND c.h = r.h")

    def unordered(self, a: Compare) -> str:
        """A relation (v, h, y) of the ends and values that are out of order."""
        return self._named("unordered", a, f"SELECT x.t AS v, x.h, y.h AS y FROM (SELECT t, h, {self._values('h')} FROM {self.ends(a.path)}) x JOIN (SELECT t, h, {self._values('h')} FROM {self.ends(Prop(a.prop))}) y ON x.t = y.t WHERE NOT {self._holds(a)}")

    def _values(self, c: str) -> str:
        """What a term is compared by, once per term and not per pair."""
        return f"{self._number(c)} AS number, {self._moment(c)} AS moment, {self._plain(c)} AS plain"

    @staticmethod
    def _holds(a: Compare) -> str:
        """Whether x, an end of the path, and y, a value of the property, are in order."""
        left, right, sign = ("y", "x", a.relation.replace(">", "<")) if a.relation[0] == ">" else ("x", "y", a.relation)
        return f"coalesce(CASE WHEN isnan({left}.number) OR isnan({right}.number) THEN false ELSE {left}.number {sign} {right}.number END, {left}.moment {sign} {right}.moment, {left}.plain {sign} {right}.plain, false)"

    def by_rows(self, s: Shape) -> str | None:
        """A relation (s, p, o) without repeated rows: the evidence of nodes of ``Rows`` that have a value out of order with one
        of the node that leads to them. Verdict and triples come from one join of the rows with that node's values, and the
        joined node belongs to every triple, so its rows are made distinct where the join left them; None for other shapes."""
        r, parts = self.rows, conjuncts(s)
        own = [x for x in parts if isinstance(x, Not) and isinstance(x.shape, Compare)]
        if r is None or len(parts) != 2 or len(own) != 1 or next(x for x in parts if x is not own[0]) != AtLeast(1, Seq(Prop("type"), Star(Prop("subClassOf"))), HasValue(r.klass)):
            return None
        a = own[0].shape
        match push_inverse(a.path):
            case Seq(Inv(Prop(k)), Prop(q)) if k in r.into & r.told and a.prop in r.told - r.into and q not in (k, a.prop, "type"):
                pass
            case _:
                return None
        p = a.prop
        rows = f"SELECT {k} AS k, node, {p} AS y, {self._values(p)} FROM {r.view} WHERE known AND {k} IS NOT NULL AND {p} IS NOT NULL"
        met = self._named("met", a, f"SELECT y.k, y.node, y.y, x.h FROM ({rows}) y JOIN (SELECT t, h, {self._values('h')} FROM {self._moves(Prop(q))}) x ON y.k = x.t WHERE NOT {self._holds(a)}")
        triples = [("node", "type", self._quote(r.klass)), ("k", k, "node"), ("node", p, "y")]
        made = ", ".join(f"named_struct('s', {x}, 'p', {self._quote(n)}, 'o', {o})" for x, n, o in triples)
        # Counting the nodes keeps their column, so that both halves read one and the same shuffle.
        body = f"SELECT made.s, made.p, made.o FROM (SELECT explode(array({made})) AS made FROM (SELECT DISTINCT k, node, y FROM {met}))"
        body += f" UNION ALL SELECT k, {self._quote(q)}, h FROM (SELECT k, h FROM {met} GROUP BY k, h HAVING count(node) > 0)"
        return self._named("evidence", s, body)

    def clashes(self, e: Path) -> str:
        """A relation (v, h) of ends that share their language tag with another end."""
        tag = self._tag("h")
        return self._named("clashes", e, f"SELECT v, h FROM (SELECT t AS v, h, count(*) OVER (PARTITION BY t, {tag}) AS n FROM (SELECT DISTINCT t, h FROM {self.ends(e)}) WHERE {tag} <> '') WHERE n > 1")

    @staticmethod
    def _tag(x: str) -> str:
        return f"""(CASE WHEN {x} LIKE '"%' THEN lower(regexp_extract({x}, r'"@([A-Za-z0-9-]+)$', 1)) ELSE '' END)"""

    @staticmethod
    def _content(x: str) -> str:
        return f"""regexp_extract({x}, r'(?s)^"(.*)"[^"]*$', 1)"""

    @staticmethod
    def _typed(x: str, kinds: tuple[str, ...], made: str) -> str:
        """The value of a literal of the kinds, by the ends of its text; null for other terms."""
        ends = [f"""WHEN endswith({x}, '"^^{k}') AND length({x}) > {len(k) + 3} THEN try_cast(substring({x}, 2, length({x}) - {len(k) + 4}) AS {made})""" for k in kinds]
        return f"""(CASE WHEN startswith({x}, '"') THEN CASE {' '.join(ends)} END END)"""

    def _number(self, x: str) -> str:
        return self._typed(x, NUMERIC, "double")

    def _moment(self, x: str) -> str:
        return self._typed(x, TEMPORAL, "timestamp_ntz")

    def _plain(self, x: str) -> str:
        return f"""(CASE WHEN startswith({x}, '"') AND endswith({x}, '"') AND length({x}) > 1 THEN substring({x}, 2, length({x}) - 2) END)"""

    def test(self, t) -> str:
        """A node test as a condition on v; a test that is a Python function has no translation."""
        lexical = f"(CASE WHEN v LIKE '\"%' THEN {self._content('v')} WHEN v LIKE '<%' THEN substring(v, 2, length(v) - 2) ELSE v END)"
        signs = {"min": ">=", "max": "<=", "above": ">", "below": "<"}
        if t.kind in signs:
            if isinstance(t.value, str):
                return f"coalesce({self._moment('v')} {signs[t.kind]} timestamp_ntz '{t.value}', false)"
            return f"coalesce(NOT isnan({self._number('v')}) AND {self._number('v')} {signs[t.kind]} {float(t.value)}D, false)"
        if t.kind == "datatype":
            value = self._number("v") if t.value in NUMERIC else self._moment("v") if t.value in TEMPORAL else None
            if t.value == "string":
                return f"{self._plain('v')} IS NOT NULL"
            return f"""(v RLIKE r'(?s)^".*"\\^\\^{t.value}$'{f" AND {value} IS NOT NULL" if value else ""})"""
        made = {
            "iri": lambda: "v LIKE '<%'",
            "literal": lambda: "v LIKE '\"%'",
            "blank": lambda: "startswith(v, '_:')",
            "pattern": lambda: f"{lexical} RLIKE {self._quote(str(t.value))}",
            "lang": lambda: f"({self._tag('v')} = {self._quote(t.value.lower())} OR startswith({self._tag('v')}, {self._quote(t.value.lower() + '-')}))",
            "minLength": lambda: f"length({lexical}) >= {int(t.value)}",
            "maxLength": lambda: f"length({lexical}) <= {int(t.value)}",
            "in": lambda: f"v IN ({', '.join(map(self._quote, t.value))})",
        }
        if t.kind not in made:
            raise TypeError(f"not translated: {t}")
        return made[t.kind]()

    @staticmethod
    def shows(s: Shape) -> bool:
        """Whether the (normal) shape has evidence at all."""
        return not isinstance(s.shape if isinstance(s, Not) and isinstance(s.shape, HasValue | Test) else s, Top | Bottom | HasValue | Test | Disj | Closed | Compare | UniqueLang)

    def evidence(self, s: Shape, nodes: str | None = None) -> str:
        """A relation (v, s, p, o), of ``nodes`` that all satisfy the shape, or of all that do; v is a node whose evidence the
        triple is, which may be one inside the shape."""
        given, nodes = nodes is not None, nodes or self.conform(s)
        within = f" WHERE v IN (SELECT v FROM {nodes})" if given else ""
        none = f"SELECT v, v AS s, v AS p, v AS o FROM {nodes} WHERE false"

        def along(e: Path, x: Shape) -> str:
            known = self._found(e, nodes)
            own = f"SELECT {'' if self._tidy(self.plan(e)) else 'DISTINCT '}t AS v, s, p, o FROM {known} WHERE {self.among(x, 'h')} AND t IN (SELECT v FROM {nodes})"
            if not self.shows(x):
                return own
            reached = self._named("nodes", ("reached", e, x, nodes), f"SELECT DISTINCT h AS v FROM {self.ends(e)} WHERE {self.among(x, 'h')} AND t IN (SELECT v FROM {nodes})")
            return f"{own} UNION ALL SELECT * FROM {self.evidence(x, reached)}"

        match s:
            case And(a, b):
                parts = conjuncts(s)
                if any(not isinstance(x, AtLeast | HasValue | Test) for x in parts) and any(self._large(x.path) for x in parts if hasattr(x, "path") and not isinstance(x.path, IdPath)):
                    self.narrow.add(nodes)
                body = f"SELECT * FROM {self.evidence(a, nodes)} UNION ALL SELECT * FROM {self.evidence(b, nodes)}"
            case Or(a, b):
                sides = [self.conform(x, nodes) if self.filters(x) else self._named("nodes", (x, "of", nodes), f"SELECT v FROM {nodes} LEFT SEMI JOIN {self.conform(x)} USING (v)") for x in (a, b)]
                body = f"SELECT * FROM {self.evidence(a, sides[0])} UNION ALL SELECT * FROM {self.evidence(b, sides[1])}"
            case AtLeast(1, e, x):
                body = along(*self.nested(e, x))
            case AtLeast(_, e, x) | ForAll(e, x):
                body = along(e, x)
            case AtMost(_, e, x):
                body = along(e, negate(x))
            case Eq(IdPath(), p) | Not(Disj(IdPath(), p)):
                body = f"SELECT s AS v, s, p, o FROM triples WHERE p = {self._quote(p)} AND s = o AND s IN (SELECT v FROM {nodes})"
            case Eq(e, p):
                body = " UNION ALL ".join(f"SELECT t AS v, s, p, o FROM {self._found(x, nodes)} WHERE t IN (SELECT v FROM {nodes})" for x in (e, Prop(p)))
            case Not(Eq(IdPath(), p)):
                body = f"SELECT s AS v, s, p, o FROM triples WHERE p = {self._quote(p)} AND s <> o AND s IN (SELECT v FROM {nodes})"
            case Not(Disj(e, p) as a) if shared := self.common(a):
                e, within = self.plan(e), ""
                shared = self._named("common", (a, nodes), f"SELECT * FROM {shared} WHERE t IN (SELECT v FROM {nodes})") if given else shared
                rest = self.sifted(self._path(e.second), ["t", "h"], shared, ["m", "h"])
                ends, q = ("m", "t") if isinstance(e.first, Inv) else ("t", "m"), next(iter(steps_of(e.first)))
                body = f"SELECT t AS v, {ends[0]} AS s, {self._quote(q)} AS p, {ends[1]} AS o FROM {shared} UNION ALL SELECT t, t, {self._quote(p)}, h FROM {shared}"
                body += f" UNION ALL SELECT r.t, r.s, r.p, r.o FROM {rest} r LEFT SEMI JOIN {shared} c ON r.t = c.m AND r.h = c.h"
            case Not(Eq(e, p) | Disj(e, p) as a):
                both = self.sides(a, isinstance(a, Disj))
                body = self._chosen(e, p, both, "h", "h", "WHERE far = 1", "WHERE near = 1")
            case Not(Compare(e, _, p) as a):
                body = self._chosen(e, p, self.unordered(a), "h", "y")
            case Not(UniqueLang(e)):
                body = f"SELECT x.t AS v, x.s, x.p, x.o FROM {self.path(e)} x LEFT SEMI JOIN {self.clashes(e)} b ON x.t = b.v AND x.h = b.h"
            case Not(Closed(props)):
                body = f"SELECT s AS v, s, p, o FROM triples WHERE p NOT IN ({', '.join(map(self._quote, sorted(props))) or 'NULL'})"
            case Top() | Bottom() | HasValue() | Test() | Not(HasValue() | Test()) | Disj() | Closed() | Compare() | UniqueLang():
                body = none
            case _:
                raise TypeError(f"not translated: {s}")
        if isinstance(s, Not) and within and body is not none:
            body = f"SELECT * FROM ({body}){within}"
        return self._named("evidence", (s, nodes), body)

    def _chosen(self, e: Path, p: str, pairs_: str, end: str, value: str, far: str = "", near: str = "") -> str:
        """Paths to the chosen ends and the property's triples to the chosen values."""
        paths = f"SELECT x.t AS v, x.s, x.p, x.o FROM {self.path(e)} x LEFT SEMI JOIN (SELECT v, {end} AS z FROM {pairs_} {far}) b ON x.t = b.v AND x.h = b.z"
        own = f"SELECT x.t, x.s, x.p, x.o FROM {self.path(Prop(p))} x LEFT SEMI JOIN (SELECT v, {value} AS z FROM {pairs_} {near}) b ON x.t = b.v AND x.h = b.z"
        return f"{paths} UNION {own}"

    def text(self, select: str) -> str:
        ctes = ",\n".join(f"{n} AS (\n  {b}\n)" for n, b in self.ctes.items())
        return f"WITH {ctes}\n{select}" if ctes else select


def sql_subgraph(shapes: list[Shape], schema: ShapeSchema | None = None, closure: Callable[[Path], str] | None = None, rows: Rows | None = None) -> str:
    t = Translator(closure, rows)
    if len(shapes) == 1 and (found := t.by_rows(to_nnf(shapes[0], schema))):
        return t.text(f"SELECT s, p, o FROM {found}")
    names = [t.evidence(to_nnf(s, schema)) for s in shapes]
    return t.text(f"SELECT DISTINCT s, p, o FROM ({' UNION ALL '.join(f'SELECT s, p, o FROM {n}' for n in names)})")


def sql_conform(s: Shape, schema: ShapeSchema | None = None, closure: Callable[[Path], str] | None = None, rows: Rows | None = None) -> str:
    """Validation as one query: only the nodes that satisfy the shape."""
    t = Translator(closure, rows)
    return t.text(f"SELECT v FROM {t.conform(to_nnf(s, schema))}")


def sql_size(sql: str) -> dict[str, int]:
    return {"lines": sql.count("\n") + 1, "characters": len(sql)}


def is_plain(df: DataFrame) -> bool:
    """Whether rows are only read, selected and renamed, so that reading them again costs no shuffle."""
    return not re.search(r"\b(Join|Aggregate|Window|Generate|Distinct|Deduplicate|Sort|Repartition\w*)\b", df._jdf.queryExecution().analyzed().toString())


def run_sql(g: TripleGraph, sql: str, others: set[str] | frozenset[str] = frozenset()) -> DataFrame:
    """Runs generated text over the graph's views; ``others`` are nodes beside those of the graph, such as constants. Properties
    that need a shuffle are written first, and so are the text's own sets that are used again or sieved. The views have names
    of their own, so requests do not meet."""
    spark, mark = g.spark, uuid.uuid4().hex[:10]
    plain = [p for p in g.parts if is_plain(g.raw(p))]
    triples, made = g.triples(plain, exact=False), [p for p in g.parts if p not in plain]
    triples = triples.unionAll(cut(g.triples(made), "triples")) if made else triples
    views = {"triples": triples}
    if re.search(r"\b(FROM|JOIN) universe\b", sql):
        ends = triples.select(F.explode(F.array("s", "o")).alias("v"))
        views["universe"] = cut(ends.union(local(spark, [(n,) for n in sorted(others)], v=pa.string())).distinct(), "universe")
    if g.rows is not None and re.search(rf"\b(FROM|JOIN) {g.rows.view}\b", sql):
        views[g.rows.view] = g.rows.make()
    parts, last = split_text(sql)

    def needed(text: str) -> list[str]:
        found = set(re.findall(r"\w+", text)) & set(parts)
        todo = list(found)
        while todo:
            new = set(re.findall(r"\w+", parts[todo.pop()])) & set(parts) - found
            found |= new
            todo += new
        return [n for n in parts if n in found]

    def run(text: str) -> DataFrame:
        own = needed(text)
        whole = (f"WITH {', '.join(f'{n} AS ({parts[n]})' for n in own)} " if own else "") + text
        return spark.sql(re.sub(r"\b(FROM|JOIN) (\w+)\b", lambda x: f"{x[1]} {x[2]}_{mark}" if x[2] in views else x[0], whole))

    for name, df in views.items():
        df.createOrReplaceTempView(f"{name}_{mark}")
    uses = lambda n: len(re.findall(rf"\b{n}\b", " ".join([last, *parts.values()])))
    for name in [n for n in parts if WRITTEN.match(n)]:
        if uses(name) > 1 or name.startswith("sifted_"):
            views[name] = cut(run(f"SELECT * FROM {name}"), name)
            views[name].createOrReplaceTempView(f"{name}_{mark}")
            del parts[name]
    return run(last)


def split_text(sql: str) -> tuple[dict[str, str], str]:
    """The named parts of a generated text, in order, and its last statement."""
    found = list(re.finditer(r"(?:^WITH |,\n)(\w+) AS \(\n  (.*)\n\)(?=,\n\w+ AS \(\n|\n)", sql))
    return {x[1]: x[2] for x in found}, sql[found[-1].end() :].lstrip() if found else sql


def closures(g: TripleGraph) -> Callable[[Path], str]:
    """A closure provider: the star's pairs over the nodes of its properties, written once, as a temporary view."""
    made: dict[Path, str] = {}

    def provide(e: Path) -> str:
        if e not in made:
            made[e] = f"closure_{hashlib.md5(repr(e).encode()).hexdigest()[:10]}"
            own = g.restrict(steps_of(e)).nodes()  # others have no step of the loop
            cut(pairs(g, e, own).select("v", "x").toDF("t", "h"), "closure").createOrReplaceTempView(made[e])
        return made[e]

    return provide
