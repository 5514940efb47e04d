"""DuckDB SQL on the base tables for shapes and tree patterns, written apart from the engine and its mapping.

The graph is one table expression per property. ``shape_sql`` follows the definitions of satisfaction and evidence one by one
and materialises every relation; ``pattern_sql`` finds a pattern's images by semi-joins up and down its tree.
"""

from __future__ import annotations

from .plans.paths import Alt, IdPath, Inv, Opt, Path, Prop, Seq, Star, push_inverse, steps_of
from .plans.patterns import PatternNode
from .plans.shapes import And, AtLeast, AtMost, Bottom, Closed, Compare, Disj, Eq, ForAll, HasValue, Not, Or, Shape, Test, Top, UniqueLang, conjuncts, negate, to_nnf
from .sources.mapping import EVENTS, SEGMENTS, SUBCLASSES


def _iri(prefix: str, *columns: str) -> str:
    return f"'<{prefix}/' || " + " || '-' || ".join(columns) + " || '>'"


def _text(x: str) -> str:
    return f"'\"' || replace(replace(replace({x}, '\\', '\\\\'), '\"', '\\\"'), chr(10), '\\n') || '\"'"


def _decimal(x: str) -> str:
    return f"'\"' || cast(cast({x} as decimal(18,2)) as varchar) || '\"^^decimal'"


def _integer(x: str) -> str:
    return f"'\"' || cast({x} as bigint) || '\"^^integer'"


def _day(x: str) -> str:
    return f"'\"' || strftime({x}, '%Y-%m-%d') || '\"^^date'"


def _plain(x: str) -> str:
    return f"'\"' || {x} || '\"'"


ORDER, CUST, SUPP, PART, NATION, REGION = _iri("order", "o_orderkey"), _iri("cust", "c_custkey"), _iri("supp", "s_suppkey"), _iri("part", "p_partkey"), _iri("nation", "n_nationkey"), _iri("region", "r_regionkey")
LINE = _iri("line", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "strftime(l_shipdate, '%Y%m%d')")
EVENT, DOC, PAGE, TURN, BENCH, VEC = _iri("event", "event_id"), _iri("doc", "doc_id"), _iri("page", "page_id"), _iri("turn", "conv_id", "turn"), _iri("bench", "item_id"), _iri("vec", "vec_id")
PART_CLASS = "'<class/part/' || split_part(p_type, ' ', 1) || '>'"
CLASS_OF = [("customer", CUST, "'<class/seg/' || c_mktsegment || '>'"), ("supplier", SUPP, "'<class/Supplier>'"), ("part", PART, PART_CLASS), ("orders", ORDER, "'<class/Order>'"), ("lineitem", LINE, "'<class/LineItem>'"), ("events", EVENT, "'<class/event/' || event_type || '>'"), ("documents", DOC, "'<class/Document>'"), ("pages", PAGE, "'<class/Page>'"), ("conversations", TURN, "'<class/Turn>'"), ("benchmark", BENCH, "'<class/BenchItem>'"), ("region", REGION, "'<class/Region>'"), ("nation", NATION, "'<class/Nation>'"), ("embeddings", VEC, "'<class/Vector>'")]
LINKS = [(f"<class/{a}>", f"<class/{b}>") for a, b in SUBCLASSES] + [(f"<class/seg/{x}>", "<class/Customer>") for x in SEGMENTS] + [(f"<class/event/{e}>", f"<class/{k}>") for e, k in EVENTS.items()]
#: Property -> (table, subject, object) sources; all are read as sets.
GRAPH: dict[str, list[tuple[str, str, str]]] = {
    "type": CLASS_OF,
    "subClassOf": [(f"(values {', '.join(f'({a!r}, {b!r})' for a, b in LINKS)}) t(a, b)", "a", "b"), ("part", PART_CLASS, "'<class/Part>'")],
    "name": [("customer", CUST, _text("c_name")), ("supplier", SUPP, _text("s_name")), ("part", PART, _text("p_name")), ("nation", NATION, _text("n_name")), ("region", REGION, _text("r_name"))],
    "inRegion": [("nation", NATION, _iri("region", "n_regionkey"))],
    "inNation": [("customer", CUST, _iri("nation", "c_nationkey")), ("supplier", SUPP, _iri("nation", "s_nationkey"))],
    "balance": [("customer", CUST, _decimal("c_acctbal")), ("supplier", SUPP, _decimal("s_acctbal"))],
    "supplies": [("lineitem", _iri("supp", "l_suppkey"), _iri("part", "l_partkey"))],
    "brand": [("part", PART, _iri("brand", "replace(p_brand, 'Brand#', '')"))],
    "size": [("part", PART, _integer("p_size"))],
    "price": [("part", PART, _decimal("p_retailprice"))],
    "placedBy": [("orders", ORDER, _iri("cust", "o_custkey"))],
    "status": [("orders", ORDER, _plain("o_orderstatus"))],
    "total": [("orders", ORDER, _decimal("o_totalprice"))],
    "orderedOn": [("orders", ORDER, _day("o_orderdate"))],
    "priority": [("orders", ORDER, _plain("o_orderpriority"))],
    "hasLine": [("lineitem", _iri("order", "l_orderkey"), LINE)],
    "inOrder": [("lineitem", LINE, _iri("order", "l_orderkey"))],
    "contains": [("lineitem", _iri("order", "l_orderkey"), _iri("part", "l_partkey"))],
    "ofPart": [("lineitem", LINE, _iri("part", "l_partkey"))],
    "fromSupplier": [("lineitem", LINE, _iri("supp", "l_suppkey"))],
    "quantity": [("lineitem", LINE, _decimal("l_quantity"))],
    "extPrice": [("lineitem", LINE, _decimal("l_extendedprice"))],
    "discount": [("lineitem", LINE, _decimal("l_discount"))],
    "tax": [("lineitem", LINE, _decimal("l_tax"))],
    "flag": [("lineitem", LINE, _plain("l_returnflag"))],
    "lineStatus": [("lineitem", LINE, _plain("l_linestatus"))],
    "shippedOn": [("lineitem", LINE, _day("l_shipdate"))],
    "byUser": [("events", EVENT, _iri("user", "user_id"))],
    "at": [("events", EVENT, "'\"' || strftime(ts, '%Y-%m-%d %H:%M:%S.%f') || '\"^^dateTime'")],
    "value": [("events", EVENT, _decimal("value"))],
    "k": [("events", EVENT, _integer("json_extract_string(props, '$.k')"))],
    "next": [("(select event_id, lead(event_id) over (partition by user_id order by ts, event_id) as after from events)", EVENT, _iri("event", "after"))],
    "excerpt": [("documents", DOC, _text("substr(text, 1, 64)") + " || '@' || lang"), ("benchmark", BENCH, _text("substr(text, 1, 64)"))],
    "source": [("documents", DOC, _iri("source", "source"))],
    "nChars": [("documents", DOC, _integer("n_chars"))],
    "canonical": [("(select doc_id, min(doc_id) over (partition by text) as first_id from documents where text is not null)", DOC, _iri("doc", "first_id"))],
    "quotes": [("(select doc_id, item_id from benchmark b join documents d on contains(d.text, b.text))", DOC, BENCH)],
    "quality": [("labels", DOC, _integer("quality"))],
    "toxic": [("labels", DOC, _integer("toxic"))],
    "url": [("pages", PAGE, _text("url"))],
    "host": [("pages", PAGE, _iri("host", "regexp_extract(url, '://([^/?#]*)', 1)"))],
    "title": [("pages", PAGE, _text("regexp_extract(html, '(?s)<title>(.*?)</title>', 1)") + " || '@' || regexp_extract(html, '<html lang=\"([a-z]+)\"', 1)")],
    "linksTo": [("(select page_id, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) as path from pages)", PAGE, "'<path' || path || '>'")],
    "inConv": [("conversations", TURN, _iri("conv", "conv_id"))],
    "role": [("conversations", TURN, _plain("role"))],
    "chars": [("conversations", TURN, _integer("length(text)"))],
    "replyTo": [("(select conv_id, turn, lag(turn) over (partition by conv_id order by turn) as previous from conversations)", TURN, _iri("turn", "conv_id", "previous"))],
    "label": [("embeddings", VEC, _iri("label", "label"))],
    "norm": [("embeddings", VEC, _decimal("sqrt(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))))"))],
}


def _quoted(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


class _Text:
    """Table expressions in the order in which they are first named. ``since`` keeps lines and orders from a date on."""

    def __init__(self, since: str | None = None) -> None:
        self.made: dict[str, str] = {}
        self.names: dict[object, str] = {}
        self.since = since

    def add(self, key: object, body: str) -> str:
        if key not in self.names:
            self.names[key] = f"r{len(self.names)}"
            self.made[self.names[key]] = body
        return self.names[key]

    def prop(self, p: str) -> str:
        cut = f" join orders on o_orderkey = l_orderkey and o_orderdate >= timestamp '{self.since}'" if self.since else ""
        sources = [f"select {s} as s, {o} as o from {t}{cut if t == 'lineitem' else ''}" for t, s, o in GRAPH[p]]
        return self.add(("prop", p), f"select distinct s, o from ({' union all '.join(sources)}) where s is not null and o is not null")

    def full(self, select: str) -> str:
        tables = ", ".join(f"{n} as materialized ({b})" for n, b in self.made.items())
        return f"with recursive {tables} {select}" if tables else select

    # Paths: pairs (v, x) and traces (v, s, p, o, x).

    def pairs(self, e: Path) -> str:
        e = push_inverse(e)
        if isinstance(e, Star):
            step, name = self.pairs(e.path), f"loop{len(self.names)}"
            return self.add(("pairs", e), f"with recursive {name}(v, x) as (select v, v from {self.nodes(e)} union select l.v, t.x from {name} l join {step} t on l.x = t.v) select v, x from {name}")
        match e:
            case Prop(n):
                body = f"select s as v, o as x from {self.prop(n)}"
            case Inv(Prop(n)):
                body = f"select o as v, s as x from {self.prop(n)}"
            case Seq(a, b):
                body = f"select distinct a.v, b.x from {self.pairs(a)} a join {self.pairs(b)} b on a.x = b.v"
            case Alt(a, b):
                body = f"select v, x from {self.pairs(a)} union select v, x from {self.pairs(b)}"
            case Opt(a):
                body = f"select v, x from {self.pairs(a)} union select v, v from {self.nodes(e)}"
            case _:
                raise TypeError(f"no pairs: {e}")
        return self.add(("pairs", e), body)

    def nodes(self, e: Path) -> str:
        """Nodes at which an empty path may matter: those of the path's properties, and all that have a class."""
        ends = " union ".join(f"select s as v from {self.prop(p)} union select o from {self.prop(p)}" for p in sorted(steps_of(e) | {"type"}))
        return self.add(("nodes", steps_of(e)), ends)

    def traces(self, e: Path) -> str:
        e = push_inverse(e)
        match e:
            case Prop(n):
                body = f"select s as v, s, '{n}' as p, o, o as x from {self.prop(n)}"
            case Inv(Prop(n)):
                body = f"select o as v, s, '{n}' as p, o, s as x from {self.prop(n)}"
            case Seq(a, b):
                body = f"select a.v, a.s, a.p, a.o, b.x from {self.traces(a)} a join {self.pairs(b)} b on a.x = b.v union select a.v, b.s, b.p, b.o, b.x from {self.pairs(a)} a join {self.traces(b)} b on a.x = b.v"
            case Alt(a, b):
                body = f"select * from {self.traces(a)} union select * from {self.traces(b)}"
            case Opt(a):
                body = f"select * from {self.traces(a)}"
            case Star(a):
                body = f"select a.v, t.s, t.p, t.o, b.x from {self.pairs(e)} a join {self.traces(a)} t on a.x = t.v join {self.pairs(e)} b on t.x = b.v"
            case _:
                raise TypeError(f"no traces: {e}")
        return self.add(("traces", e), body)

    # Node tests and shapes as conditions on a column.

    @staticmethod
    def test(kind: str, x: object, v: str) -> str:
        lexical = f"(case when {v} like '\"%' then regexp_extract({v}, '(?s)^\"(.*)\"[^\"]*$', 1) when {v} like '<%' then substr({v}, 2, length({v}) - 2) else {v} end)"
        number, moment = _Text.number(v), _Text.moment(v)
        signs = {"min": ">=", "max": "<=", "above": ">", "below": "<"}
        if kind in signs:
            return f"coalesce({moment} {signs[kind]} timestamp '{x}', false)" if isinstance(x, str) else f"coalesce({number} {signs[kind]} {x}, false)"
        return {
            "iri": lambda: f"{v} like '<%'",
            "literal": lambda: f"{v} like '\"%'",
            "blank": lambda: f"{v} like '\\_:%' escape '\\'",
            "pattern": lambda: f"regexp_matches({lexical}, {_quoted(str(x))})",
            "lang": lambda: f"(lower(regexp_extract({v}, '\"@([A-Za-z0-9-]+)$', 1)) = '{x}' or lower(regexp_extract({v}, '\"@([A-Za-z0-9-]+)$', 1)) like '{x}-%')",
            "datatype": lambda: f"({v} like '\"%\"')" if x == "string" else f"({v} like '\"%\"^^{x}' and {moment if x in ('date', 'dateTime') else number} is not null)",
            "minLength": lambda: f"length({lexical}) >= {x}",
            "maxLength": lambda: f"length({lexical}) <= {x}",
            "in": lambda: f"{v} in ({', '.join(map(_quoted, x))})",  # type: ignore[call-overload]
        }[kind]()

    @staticmethod
    def number(v: str) -> str:
        return f"(case when regexp_matches({v}, '\"\\^\\^(integer|decimal|double)$') then try_cast(regexp_extract({v}, '^\"(.*)\"', 1) as double) end)"

    @staticmethod
    def moment(v: str) -> str:
        return f"(case when regexp_matches({v}, '\"\\^\\^(date|dateTime)$') then try_cast(regexp_extract({v}, '^\"(.*)\"', 1) as timestamp) end)"

    def ordered(self, x: str, sign: str, y: str) -> str:
        plain = f"case when {x} like '\"%\"' and {y} like '\"%\"' then {x} {sign} {y} end"
        return f"coalesce({self.number(x)} {sign} {self.number(y)}, {self.moment(x)} {sign} {self.moment(y)}, {plain}, false)"

    def own(self, p: str) -> str:
        return f"select s as v, o as x from {self.prop(p)}"

    def broken(self, a: Shape) -> str:
        """A relation of v (and more): what breaks the atom."""
        match a:
            case Eq(IdPath(), p):
                raise TypeError("handled as a condition")
            case Eq(e, p):
                body = f"select v, x, max(far) as far, max(near) as near from (select v, x, 1 as far, 0 as near from {self.pairs(e)} union all select v, x, 0, 1 from ({self.own(p)})) group by v, x having max(far) <> max(near)"
            case Disj(e, p):
                body = f"select v, x from {self.pairs(e)} intersect {self.own(p)}"
            case Closed(props):
                outside = [p for p in GRAPH if p not in props]
                body = " union ".join(f"select s as v, s, '{p}' as p, o from {self.prop(p)}" for p in outside)
            case Compare(e, sign, p):
                body = f"select a.v, a.x, b.x as y from {self.pairs(e)} a join ({self.own(p)}) b on a.v = b.v where not {self.ordered('a.x', sign, 'b.x')}"
            case UniqueLang(e):
                tag = "lower(regexp_extract(x, '\"@([A-Za-z0-9-]+)$', 1))"
                body = f"select v, x from (select v, x, count(*) over (partition by v, {tag}) as n from {self.pairs(e)} where x like '\"%' and {tag} <> '') where n > 1"
            case _:
                raise TypeError(f"no atom: {a}")
        return self.add(("broken", a), body)

    def cond(self, s: Shape, v: str) -> str:
        match s:
            case Top():
                return "true"
            case Bottom():
                return "false"
            case HasValue(c):
                return f"{v} = {_quoted(c)}"
            case Test(t):
                return self.test(t.kind, t.value, v)
            case And(a, b):
                return f"({self.cond(a, v)} and {self.cond(b, v)})"
            case Or(a, b):
                return f"({self.cond(a, v)} or {self.cond(b, v)})"
            case AtLeast(n, e, x):
                return f"{v} in (select v from {self.many(e, x, n)})" if n else "true"
            case AtMost(n, e, x):
                return f"{v} not in (select v from {self.many(e, x, n + 1)})"
            case ForAll(e, x):
                return f"{v} not in (select v from {self.many(e, negate(x), 1)})"
            case Eq(IdPath(), p):
                return f"{v} in (select s from {self.prop(p)} group by s having count(*) = 1 and min(o) = s)"
            case Disj(IdPath(), p):
                return f"{v} not in (select s from {self.prop(p)} where s = o)"
            case Not(HasValue() | Test() | Eq(IdPath()) | Disj(IdPath()) as a):
                return f"not ({self.cond(a, v)})"
            case Not(a):
                return f"{v} in (select v from {self.broken(a)})"
        return f"{v} not in (select v from {self.broken(s)})"

    def many(self, e: Path, x: Shape, n: int) -> str:
        return self.add(("many", e, x, n), f"select v from {self.pairs(e)} where {self.cond(x, 'x')} group by v having count(*) >= {n}")

    # Evidence of the nodes of a relation.

    def evidence(self, s: Shape, good: str) -> list[str]:
        """Selects of s, p, o for nodes that satisfy the shape."""
        inside = f"v in (select v from {good})"
        match s:
            case And(a, b):
                return self.evidence(a, good) + self.evidence(b, good)
            case Or(a, b):
                sides = [(x, self.add(("side", x, good), f"select v from {good} where {self.cond(x, 'v')}")) for x in (a, b)]
                return [t for x, side in sides for t in self.evidence(x, side)]
            case AtLeast(_, e, x) | ForAll(e, x):
                return self.along(e, x, good)
            case AtMost(_, e, x):
                return self.along(e, negate(x), good)
            case Eq(IdPath(), p) | Not(Disj(IdPath(), p)):
                return [f"select s, '{p}' as p, o from {self.prop(p)} where s = o and s in (select v from {good})"]
            case Not(Eq(IdPath(), p)):
                return [f"select s, '{p}' as p, o from {self.prop(p)} where s <> o and s in (select v from {good})"]
            case Eq(e, p):
                return self.along(e, Top(), good) + self.along(Prop(p), Top(), good)
            case Not(Eq(e, p) as a):
                bad = self.broken(a)
                return [f"select s, p, o from {self.traces(e)} t where {inside} and (v, x) in (select (v, x) from {bad} where far = 1)", f"select s, '{p}' as p, o from {self.prop(p)} where s in (select v from {good}) and (s, o) in (select (v, x) from {bad} where near = 1)"]
            case Not(Disj(e, p) as a):
                bad = self.broken(a)
                return [f"select s, p, o from {self.traces(e)} t where {inside} and (v, x) in (select (v, x) from {bad})", f"select s, '{p}' as p, o from {self.prop(p)} where s in (select v from {good}) and (s, o) in (select (v, x) from {bad})"]
            case Not(Compare(e, _, p) as a):
                bad = self.broken(a)
                return [f"select s, p, o from {self.traces(e)} t where {inside} and (v, x) in (select (v, x) from {bad})", f"select s, '{p}' as p, o from {self.prop(p)} where s in (select v from {good}) and (s, o) in (select (v, y) from {bad})"]
            case Not(UniqueLang(e) as a):
                return [f"select s, p, o from {self.traces(e)} t where {inside} and (v, x) in (select (v, x) from {self.broken(a)})"]
            case Not(Closed() as a):
                return [f"select s, p, o from {self.broken(a)} where {inside}"]
        return []

    def along(self, e: Path, x: Shape, good: str) -> list[str]:
        if isinstance(x, Bottom):
            return []
        ends = self.add(("ends", e, x, good), f"select distinct x as v from {self.pairs(e)} where v in (select v from {good}) and {self.cond(x, 'x')}")
        return [f"select s, p, o from {self.traces(e)} where v in (select v from {good}) and x in (select v from {ends})", *self.evidence(x, ends)]


def _class_of(s: Shape) -> str | None:
    """The class of a class target."""
    match s:
        case AtLeast(1, Seq(Prop("type"), Star(Prop("subClassOf"))), HasValue(c)):
            return c
    return None


def _candidates(t: _Text, s: Shape) -> str:
    """A relation of nodes that holds all that satisfy the shape: those of its class target, or all nodes of its paths."""
    for part in conjuncts(s):
        if _class_of(part):
            return t.add(("target", part), f"select distinct s as v from {t.prop('type')} where {t.cond(part, 's')}")
    named: set[str] = set()

    def walk(x: Shape) -> None:
        named.update(steps_of(getattr(x, "path", None)))
        named.update({x.prop} if isinstance(x, Eq | Disj | Compare) else ())
        for inner in ("left", "right", "shape"):
            if hasattr(x, inner):
                walk(getattr(x, inner))

    walk(s)
    return t.add(("all", frozenset(named)), " union ".join(f"select s as v from {t.prop(p)} union select o from {t.prop(p)}" for p in sorted(named)))


def nodes_sql(s: Shape, since: str | None = None) -> str:
    """v of every node that satisfies the shape, among those of its class target or paths."""
    t, s = _Text(since), to_nnf(s)
    v = _candidates(t, s)
    return t.full(f"select distinct v from {v} where {t.cond(s, 'v')}")


def shape_sql(*shapes: Shape, since: str | None = None) -> str:
    """s, p, o: the union of the shapes' evidence."""
    t, found = _Text(since), []
    for s in map(to_nnf, shapes):
        good = t.add(("good", s), f"select distinct v from {_candidates(t, s)} where {t.cond(s, 'v')}")
        found += t.evidence(s, good)
    return t.full(f"select distinct s, p, o from ({' union all '.join(found)})" if found else "select '' as s, '' as p, '' as o where false")




def pattern_sql(pattern: PatternNode) -> str:
    """s, p, o: the triples of all solutions of a tree pattern, and those that show the classes of its nodes."""
    t = _Text()
    fits: dict[str, str | None] = {}

    def below(classes: tuple[str, ...]) -> str:
        listed = ", ".join(f"('<class/{c}>')" for c in classes)
        return t.add(("below", classes), f"with recursive b(c) as (select * from (values {listed}) w(c) union select s from b join {t.prop('subClassOf')} on o = c) select c from b")

    def fit(n: PatternNode, at: str) -> str | None:
        """A relation of the nodes that can stand here, None for any."""
        asks = []
        if n.classes:
            asks.append(f"v in (select s from {t.prop('type')} where o in (select c from {below(n.classes)}))")
        if n.value is not None:
            asks.append(f"v = {_quoted(n.value)}")
        if n.test is not None:
            asks.append(t.test(n.test.kind, n.test.value, "v"))
        sources = []
        for i, e in enumerate(n.edges):
            kid, (near, far) = fit(e.node, f"{at}_{i}"), ("o", "s") if e.prop.startswith("^") else ("s", "o")
            table = t.prop(e.prop.lstrip("^"))
            known = f"select {near} from {table}" + (f" where {far} in (select v from {kid})" if kid else "")
            if e.mode != "optional":
                asks.append(f"v {'not ' if e.mode == 'absent' else ''}in ({known})")
            if e.mode == "required":
                sources.append(f"select {near} as v from {table}")
        if n.classes:
            sources.insert(0, f"select s as v from {t.prop('type')}")
        fits[at] = None
        if asks:
            base = sources[0] if sources else bases[at]
            fits[at] = t.add(("fit", at), f"select distinct v from ({base}) where {' and '.join(asks)}")
        return fits[at]

    bases: dict[str, str] = {}

    def prepare(n: PatternNode, at: str) -> None:
        for i, e in enumerate(n.edges):
            far = "s" if e.prop.startswith("^") else "o"
            bases[f"{at}_{i}"] = f"select {far} as v from {t.prop(e.prop.lstrip('^'))}"
            prepare(e.node, f"{at}_{i}")

    prepare(pattern, "n")
    fit(pattern, "n")
    found: list[str] = []

    def down(n: PatternNode, at: str, here: str) -> None:
        if n.classes:
            typed = t.add(("typed", at), f"select s, o from {t.prop('type')} where s in (select v from {here}) and o in (select c from {below(n.classes)})")
            climbs = t.add(("climb", at), f"with recursive w(c) as (select distinct o from {typed} union select l.o from w join {t.prop('subClassOf')} l on l.s = c where l.o in (select c from {below(n.classes)})) select c from w")
            found.append(f"select s, 'type' as p, o from {typed}")
            found.append(f"select s, 'subClassOf' as p, o from {t.prop('subClassOf')} where s in (select c from {climbs}) and o in (select c from {below(n.classes)})")
        for i, e in enumerate(n.edges):
            if e.mode == "absent":
                continue
            kid, (near, far) = fits[f"{at}_{i}"], ("o", "s") if e.prop.startswith("^") else ("s", "o")
            p = e.prop.lstrip("^")
            step = t.add(("step", at, i), f"select s, o from {t.prop(p)} where {near} in (select v from {here})" + (f" and {far} in (select v from {kid})" if kid else ""))
            found.append(f"select s, '{p}' as p, o from {step}")
            if e.node.edges or e.node.classes:
                down(e.node, f"{at}_{i}", t.add(("at", f"{at}_{i}"), f"select distinct {far} as v from {step}"))

    down(pattern, "n", str(fits["n"]))
    return t.full(f"select distinct s, p, o from ({' union all '.join(found)})")
