"""Satisfaction and evidence of shapes on a small set of triples, straight from the definitions, with sets and path search."""

from __future__ import annotations

import re

from shapegraph.plans.paths import Alt, IdPath, Inv, Opt, Path, Prop, Seq, Star
from shapegraph.plans.shapes import And, AtLeast, AtMost, Bottom, Closed, Compare, Disj, Eq, ForAll, HasValue, Not, Or, Shape, Test, Top, UniqueLang, negate, to_nnf

Triple = tuple[str, str, str]


class Reference:
    def __init__(self, triples: set[Triple]):
        self.triples = triples
        self.nodes = {x for s, _, o in triples for x in (s, o)}

    def pairs(self, e: Path) -> set[tuple[str, str]]:
        match e:
            case IdPath():
                return {(n, n) for n in self.nodes}
            case Prop(p):
                return {(s, o) for s, q, o in self.triples if q == p}
            case Inv(a):
                return {(y, x) for x, y in self.pairs(a)}
            case Seq(a, b):
                return {(x, z) for x, y in self.pairs(a) for w, z in self.pairs(b) if y == w}
            case Alt(a, b):
                return self.pairs(a) | self.pairs(b)
            case Opt(a):
                return self.pairs(a) | {(n, n) for n in self.nodes}
            case Star(a):
                step, out = self.pairs(a), {(n, n) for n in self.nodes}
                while True:
                    more = out | {(x, z) for x, y in out for w, z in step if y == w}
                    if more == out:
                        return out
                    out = more
        raise TypeError(e)

    def ends(self, e: Path, v: str) -> set[str]:
        return {y for x, y in self.pairs(e) if x == v}

    def trace(self, e: Path, v: str, x: str) -> set[Triple]:
        """Triples on any path of e from v to x."""
        match e:
            case IdPath():
                return set()
            case Prop(p):
                return {(v, p, x)} & self.triples
            case Inv(a):
                return self.trace(a, x, v)
            case Seq(a, b):
                return {t for y in self.ends(a, v) if x in self.ends(b, y) for t in self.trace(a, v, y) | self.trace(b, y, x)}
            case Alt(a, b):
                return self.trace(a, v, x) | self.trace(b, v, x)
            case Opt(a):
                return self.trace(a, v, x)
            case Star(a):
                return {t for y in self.ends(e, v) for z in self.ends(a, y) if x in self.ends(e, z) for t in self.trace(a, y, z)}
        raise TypeError(e)

    def _tag(self, x: str) -> str:
        found = re.search(r'"@([A-Za-z0-9-]+)$', x)
        return found.group(1).lower() if found else ""

    def _ordered(self, x: str, sign: str, y: str) -> bool:
        both = [re.fullmatch(r'"(.*)"\^\^(integer|decimal)', z) for z in (x, y)]
        plain = [re.fullmatch(r'"(.*)"', z) for z in (x, y)]
        if all(both):
            a, b = (float(m.group(1)) for m in both)
        elif all(plain):
            a, b = (m.group(1) for m in plain)
        else:
            return False
        return {"<": a < b, "<=": a <= b, ">": a > b, ">=": a >= b}[sign]

    def holds(self, s: Shape, v: str) -> bool:
        match s:
            case Top():
                return True
            case Bottom():
                return False
            case HasValue(c):
                return v == c
            case Test(t):
                return {"iri": v.startswith("<"), "literal": v.startswith('"')}[t.kind]
            case Not(a):
                return not self.holds(a, v)
            case And(a, b):
                return self.holds(a, v) and self.holds(b, v)
            case Or(a, b):
                return self.holds(a, v) or self.holds(b, v)
            case AtLeast(n, e, x):
                return sum(self.holds(x, y) for y in self.ends(e, v)) >= n
            case AtMost(n, e, x):
                return sum(self.holds(x, y) for y in self.ends(e, v)) <= n
            case ForAll(e, x):
                return all(self.holds(x, y) for y in self.ends(e, v))
            case Eq(e, p):
                return ({v} if isinstance(e, IdPath) else self.ends(e, v)) == self.ends(Prop(p), v)
            case Disj(e, p):
                return not ({v} if isinstance(e, IdPath) else self.ends(e, v)) & self.ends(Prop(p), v)
            case Closed(props):
                return all(p in props for s2, p, _ in self.triples if s2 == v)
            case Compare(e, sign, p):
                return all(self._ordered(x, sign, y) for x in self.ends(e, v) for y in self.ends(Prop(p), v))
            case UniqueLang(e):
                tags = [self._tag(x) for x in self.ends(e, v) if self._tag(x)]
                return len(tags) == len(set(tags))
        raise TypeError(s)

    def evidence(self, s: Shape, v: str) -> set[Triple]:
        return self._evidence(to_nnf(s), v)

    def _evidence(self, s: Shape, v: str) -> set[Triple]:
        if not self.holds(s, v):
            return set()
        match s:
            case And(a, b) | Or(a, b):
                return self._evidence(a, v) | self._evidence(b, v)
            case AtLeast(_, e, x) | ForAll(e, x):
                return {t for y in self.ends(e, v) if self.holds(x, y) for t in self.trace(e, v, y) | self._evidence(x, y)}
            case AtMost(_, e, x):
                x = negate(x)
                return {t for y in self.ends(e, v) if self.holds(x, y) for t in self.trace(e, v, y) | self._evidence(x, y)}
            case Eq(IdPath(), p) | Not(Disj(IdPath(), p)):
                return {(v, p, v)}
            case Not(Eq(IdPath(), p)):
                return {(v, p, y) for y in self.ends(Prop(p), v) if y != v}
            case Eq(e, p):
                return {t for y in self.ends(e, v) for t in self.trace(e, v, y)} | {(v, p, y) for y in self.ends(Prop(p), v)}
            case Not(Eq(e, p)):
                far, near = self.ends(e, v), self.ends(Prop(p), v)
                return {t for y in far - near for t in self.trace(e, v, y)} | {(v, p, y) for y in near - far}
            case Not(Disj(e, p)):
                return {t for y in self.ends(e, v) & self.ends(Prop(p), v) for t in self.trace(e, v, y) | {(v, p, y)}}
            case Not(Compare(e, sign, p)):
                bad = [(x, y) for x in self.ends(e, v) for y in self.ends(Prop(p), v) if not self._ordered(x, sign, y)]
                return {t for x, y in bad for t in self.trace(e, v, x) | {(v, p, y)}}
            case Not(UniqueLang(e)):
                tags = [self._tag(x) for x in self.ends(e, v)]
                return {t for x in self.ends(e, v) if self._tag(x) and tags.count(self._tag(x)) > 1 for t in self.trace(e, v, x)}
            case Not(Closed(props)):
                return {t for t in self.triples if t[0] == v and t[1] not in props}
        return set()
