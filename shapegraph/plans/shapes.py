"""Shapes, node tests, negation normal form, simplification, schemas and targets."""

from __future__ import annotations

import json
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions import terms
from .paths import ID, Path, Prop, parse_path, path, path_text


@dataclass(frozen=True)
class NodeTest:
    """kind: iri, literal, blank, pattern, datatype, lang, min, max, above, below, minLength, maxLength, in, column."""

    kind: str
    value: object = None

    def column(self, v: Column) -> Column:
        x = self.value
        made = {
            "iri": lambda: terms.is_iri(v),
            "literal": lambda: terms.is_literal(v),
            "blank": lambda: terms.is_blank(v),
            "pattern": lambda: terms.lexical(v).rlike(str(x)),
            "datatype": lambda: (terms.datatype(v) == str(x)) & (terms.number(v).isNotNull() if x in terms.NUMERIC else terms.instant(v).isNotNull() if x in terms.TEMPORAL else F.lit(True)),
            "lang": lambda: (terms.language(v) == str(x).lower()) | terms.language(v).startswith(f"{str(x).lower()}-"),
            "min": lambda: self._scale(v) >= self._bound(),
            "max": lambda: self._scale(v) <= self._bound(),
            "above": lambda: self._scale(v) > self._bound(),
            "below": lambda: self._scale(v) < self._bound(),
            "minLength": lambda: F.length(terms.lexical(v)) >= int(x),  # type: ignore[call-overload]
            "maxLength": lambda: F.length(terms.lexical(v)) <= int(x),  # type: ignore[call-overload]
            "in": lambda: v.isin(*x),  # type: ignore[misc]
            "column": lambda: x(v),  # type: ignore[operator]
        }[self.kind]()
        return F.coalesce(made, F.lit(False))

    def _scale(self, v: Column) -> Column:
        """Numbers for a bound that is a number, times for one that is text such as 2001-07-01."""
        return terms.instant(v) if isinstance(self.value, str) else F.when(~F.isnan(terms.number(v)), terms.number(v))

    def _bound(self) -> Column:
        return F.lit(self.value).cast("timestamp_ntz") if isinstance(self.value, str) else F.lit(float(self.value))  # type: ignore[arg-type]


class Shape:
    def __and__(self, other: Shape) -> Shape:
        return And(self, other)

    def __or__(self, other: Shape) -> Shape:
        return Or(self, other)

    def __invert__(self) -> Shape:
        return Not(self)


@dataclass(frozen=True)
class Top(Shape):
    pass


@dataclass(frozen=True)
class Bottom(Shape):
    pass


@dataclass(frozen=True)
class HasValue(Shape):
    node: str


@dataclass(frozen=True)
class Test(Shape):
    test: NodeTest


@dataclass(frozen=True)
class HasShape(Shape):
    name: str


@dataclass(frozen=True)
class Eq(Shape):
    path: Path
    prop: str


@dataclass(frozen=True)
class Disj(Shape):
    path: Path
    prop: str


@dataclass(frozen=True)
class Closed(Shape):
    props: frozenset[str]


@dataclass(frozen=True)
class Compare(Shape):
    """relation: <, <=, >, >= between every path end and every value of the property."""

    path: Path
    relation: str
    prop: str

    def holds(self, x: Column, y: Column) -> Column:
        return {"<": lambda: terms.less(x, y), "<=": lambda: terms.less_eq(x, y), ">": lambda: terms.less(y, x), ">=": lambda: terms.less_eq(y, x)}[self.relation]()


@dataclass(frozen=True)
class UniqueLang(Shape):
    path: Path


@dataclass(frozen=True)
class Not(Shape):
    shape: Shape


@dataclass(frozen=True)
class And(Shape):
    left: Shape
    right: Shape


@dataclass(frozen=True)
class Or(Shape):
    left: Shape
    right: Shape


@dataclass(frozen=True)
class AtLeast(Shape):
    n: int
    path: Path
    shape: Shape


@dataclass(frozen=True)
class AtMost(Shape):
    n: int
    path: Path
    shape: Shape


@dataclass(frozen=True)
class ForAll(Shape):
    path: Path
    shape: Shape


TOP, BOTTOM = Top(), Bottom()


def exactly(n: int, e: Path, shape: Shape = TOP) -> Shape:
    return And(AtLeast(n, e, shape), AtMost(n, e, shape))


def some(e: Path | str, shape: Shape = TOP, n: int = 1) -> Shape:
    return AtLeast(n, parse_path(e) if isinstance(e, str) else e, shape)


def all_of(*shapes: Shape) -> Shape:
    return reduce(And, shapes) if shapes else TOP


def any_of(*shapes: Shape) -> Shape:
    return reduce(Or, shapes) if shapes else BOTTOM


def test(kind: str, value: object = None) -> Shape:
    return Test(NodeTest(kind, value))


def less_than(e: str, p: str) -> Shape:
    return Compare(parse_path(e), "<", p)


# Targets.


def node_target(c: str) -> Shape:
    return HasValue(c)


def class_target(name: str) -> Shape:
    return AtLeast(1, path("type", "subClassOf*"), HasValue(f"<class/{name}>"))


def subjects_of(p: str) -> Shape:
    return AtLeast(1, Prop(p), TOP)


def objects_of(p: str) -> Shape:
    return AtLeast(1, path(f"^{p}"), TOP)


def is_monotone(s: Shape) -> bool:
    """Syntactic: more triples never make a node lose the shape."""
    match s:
        case Top() | Bottom() | HasValue() | Test():
            return True
        case And(a, b) | Or(a, b):
            return is_monotone(a) and is_monotone(b)
        case AtLeast(_, _, x):
            return is_monotone(x)
        case Not(HasValue() | Test() | Disj() | Closed() | Compare() | UniqueLang()):
            return True
    return False


# Rewritings.


def negate(s: Shape, schema: ShapeSchema | None = None) -> Shape:
    """The negation in normal form: only atoms carry a Not."""
    match s:
        case Top():
            return BOTTOM
        case Bottom():
            return TOP
        case Not(x):
            return to_nnf(x, schema)
        case And(a, b):
            return Or(negate(a, schema), negate(b, schema))
        case Or(a, b):
            return And(negate(a, schema), negate(b, schema))
        case AtLeast(n, e, x):
            return AtMost(n - 1, e, to_nnf(x, schema)) if n else BOTTOM
        case AtMost(n, e, x):
            return AtLeast(n + 1, e, to_nnf(x, schema))
        case ForAll(e, x):
            return AtLeast(1, e, negate(x, schema))
        case HasShape(name):
            return negate(schema.lookup(name), schema) if schema else Not(s)
    return Not(s)


def to_nnf(s: Shape, schema: ShapeSchema | None = None) -> Shape:
    match s:
        case Not(x):
            return negate(x, schema)
        case And(a, b):
            return And(to_nnf(a, schema), to_nnf(b, schema))
        case Or(a, b):
            return Or(to_nnf(a, schema), to_nnf(b, schema))
        case AtLeast(n, e, x):
            return AtLeast(n, e, to_nnf(x, schema))
        case AtMost(n, e, x):
            return AtMost(n, e, to_nnf(x, schema))
        case ForAll(e, x):
            return ForAll(e, to_nnf(x, schema))
        case HasShape(name):
            return to_nnf(schema.lookup(name), schema) if schema else s
    return s


def simplify(s: Shape, keep_evidence: bool = True) -> Shape:
    """Drops what decides nothing. ``>= 0`` and ``forall top`` carry evidence, so they stay unless only verdicts count."""
    match s:
        case And(a, b):
            a, b = simplify(a, keep_evidence), simplify(b, keep_evidence)
            return BOTTOM if BOTTOM in (a, b) else b if a == TOP else a if b in (TOP, a) else And(a, b)
        case Or(a, b):
            a, b = simplify(a, keep_evidence), simplify(b, keep_evidence)
            return b if a == BOTTOM else a if b in (BOTTOM, a) else TOP if not keep_evidence and TOP in (a, b) else Or(a, b)
        case Not(x):
            return Not(simplify(x, keep_evidence))
        case AtLeast(n, e, x):
            return TOP if n == 0 and not keep_evidence else AtLeast(n, e, simplify(x, keep_evidence))
        case AtMost(n, e, x):
            x = simplify(x, keep_evidence)
            return TOP if x == BOTTOM else AtMost(n, e, x)
        case ForAll(e, x):
            x = simplify(x, keep_evidence)
            return TOP if x == TOP and not keep_evidence else ForAll(e, x)
    return s


def reduce_tests(s: Shape) -> Shape:
    """Node tests replaced by top."""
    match s:
        case Test():
            return TOP
        case Not(x):
            return Not(reduce_tests(x))
        case And(a, b):
            return And(reduce_tests(a), reduce_tests(b))
        case Or(a, b):
            return Or(reduce_tests(a), reduce_tests(b))
        case AtLeast(n, e, x):
            return AtLeast(n, e, reduce_tests(x))
        case AtMost(n, e, x):
            return AtMost(n, e, reduce_tests(x))
        case ForAll(e, x):
            return ForAll(e, reduce_tests(x))
    return s


def is_local(s: Shape) -> bool:
    """Decided by the node alone."""
    match s:
        case Top() | Bottom() | Test() | HasValue():
            return True
        case Not(x):
            return is_local(x)
        case And(a, b) | Or(a, b):
            return is_local(a) and is_local(b)
    return False


def holds(s: Shape, v: Column) -> Column:
    """A local shape as a condition on a node, never null."""
    match s:
        case Top():
            return F.lit(True)
        case Bottom():
            return F.lit(False)
        case Test(t):
            return t.column(v)
        case HasValue(c):
            return v == c
        case Not(x):
            return ~holds(x, v)
        case And(a, b):
            return holds(a, v) & holds(b, v)
        case Or(a, b):
            return holds(a, v) | holds(b, v)
    raise TypeError(f"not local: {s}")


def conjuncts(s: Shape) -> list[Shape]:
    return conjuncts(s.left) + conjuncts(s.right) if isinstance(s, And) else [s]


def cost(s: Shape) -> int:
    """A rough order of conjuncts: tests, then atoms, then quantifiers by depth."""
    match s:
        case Top() | Bottom() | HasValue() | Test() | Not(HasValue() | Test()):
            return 0
        case And(a, b) | Or(a, b):
            return cost(a) + cost(b)
        case AtLeast(n, e, x) | AtMost(n, e, x):
            return 10 * (1 + path_text(e).count("/") + 5 * path_text(e).count("*")) + cost(x) + n
        case ForAll(e, x):
            return 12 * (1 + path_text(e).count("/")) + cost(x)
    return 20


def constants(s: Shape) -> set[str]:
    match s:
        case HasValue(c):
            return {c}
        case Not(x) | AtLeast(_, _, x) | AtMost(_, _, x) | ForAll(_, x):
            return constants(x)
        case And(a, b) | Or(a, b):
            return constants(a) | constants(b)
    return set()


def references(s: Shape) -> set[str]:
    match s:
        case HasShape(n):
            return {n}
        case Not(x) | AtLeast(_, _, x) | AtMost(_, _, x) | ForAll(_, x):
            return references(x)
        case And(a, b) | Or(a, b):
            return references(a) | references(b)
    return set()


@dataclass(frozen=True)
class ShapeDef:
    name: str
    shape: Shape
    target: Shape = BOTTOM


@dataclass
class ShapeSchema:
    defs: list[ShapeDef] = field(default_factory=list)

    def lookup(self, name: str) -> Shape:
        return next((d.shape for d in self.defs if d.name == name), TOP)

    def check(self) -> ShapeSchema:
        """Raises ValueError on a repeated name or a cycle of references."""
        names = [d.name for d in self.defs]
        if len(set(names)) < len(names):
            raise ValueError("a shape name is defined twice")
        uses = {d.name: references(d.shape) for d in self.defs}

        def visit(name: str, trail: tuple[str, ...]) -> None:
            if name in trail:
                raise ValueError(f"recursive schema: {' -> '.join((*trail, name))}")
            for x in uses.get(name, ()):
                visit(x, (*trail, name))

        for name in names:
            visit(name, ())
        return self

    def requests(self) -> list[Shape]:
        return [And(d.shape, d.target) for d in self.defs]

    @classmethod
    def from_json(cls, text: str) -> ShapeSchema:
        """[{"name", "shape", "target"}], shapes and targets in the form of :func:`shape_from`."""
        return cls([ShapeDef(d["name"], shape_from(d["shape"]), shape_from(d.get("target", "bottom"))) for d in json.loads(text)]).check()


def shape_from(x: object) -> Shape:
    """From JSON values: "top", "bottom", {"hasValue": c}, {"class": c}, {"atLeast": [n, path, shape]}, {"and": [...]} and so on."""
    if x in ("top", "bottom"):
        return TOP if x == "top" else BOTTOM
    if not isinstance(x, dict) or len(x) != 1:
        raise ValueError(f"no shape: {x!r}")
    (key, v), both = next(iter(x.items())), lambda e: ID if e == "id" else parse_path(e)
    made = {
        "hasValue": lambda: HasValue(v), "hasShape": lambda: HasShape(v), "class": lambda: class_target(v), "subjectsOf": lambda: subjects_of(v), "objectsOf": lambda: objects_of(v),
        "not": lambda: Not(shape_from(v)), "and": lambda: all_of(*map(shape_from, v)), "or": lambda: any_of(*map(shape_from, v)),
        "atLeast": lambda: AtLeast(v[0], parse_path(v[1]), shape_from(v[2])), "atMost": lambda: AtMost(v[0], parse_path(v[1]), shape_from(v[2])),
        "exactly": lambda: exactly(v[0], parse_path(v[1]), shape_from(v[2])), "all": lambda: ForAll(parse_path(v[0]), shape_from(v[1])),
        "eq": lambda: Eq(both(v[0]), v[1]), "disj": lambda: Disj(both(v[0]), v[1]), "closed": lambda: Closed(frozenset(v)),
        "compare": lambda: Compare(parse_path(v[0]), v[1], v[2]), "uniqueLang": lambda: UniqueLang(parse_path(v)), "test": lambda: test(*v),
    }
    if key not in made:
        raise ValueError(f"no shape: {x!r}")
    return made[key]()
