"""Path expressions and their position automata."""

from __future__ import annotations

from dataclasses import dataclass


class Path:
    def __truediv__(self, other: Path) -> Path:
        return Seq(self, other)

    def __or__(self, other: Path) -> Path:
        return Alt(self, other)


@dataclass(frozen=True)
class Prop(Path):
    name: str


@dataclass(frozen=True)
class Inv(Path):
    path: Path


@dataclass(frozen=True)
class Seq(Path):
    first: Path
    second: Path


@dataclass(frozen=True)
class Alt(Path):
    first: Path
    second: Path


@dataclass(frozen=True)
class Star(Path):
    path: Path


@dataclass(frozen=True)
class Opt(Path):
    path: Path


@dataclass(frozen=True)
class IdPath(Path):
    """The focus node; only as the first argument of Eq and Disj."""


ID = IdPath()


def path(*steps: str) -> Path:
    """A chain of properties; a leading ``^`` inverts, a trailing ``*`` repeats."""
    out: Path | None = None
    for step in steps:
        leaf: Path = Prop(step.strip("^*"))
        leaf = Inv(leaf) if step.startswith("^") else leaf
        leaf = Star(leaf) if step.endswith("*") else leaf
        out = leaf if out is None else Seq(out, leaf)
    assert out is not None
    return out


def push_inverse(e: Path, turned: bool = False) -> Path:
    """The same relation with inverses on properties only."""
    match e:
        case Prop():
            return Inv(e) if turned else e
        case Inv(p):
            return push_inverse(p, not turned)
        case Seq(a, b):
            return Seq(push_inverse(b, True), push_inverse(a, True)) if turned else Seq(push_inverse(a), push_inverse(b))
        case Alt(a, b):
            return Alt(push_inverse(a, turned), push_inverse(b, turned))
        case Star(p):
            return Star(push_inverse(p, turned))
        case Opt(p):
            return Opt(push_inverse(p, turned))
    raise TypeError(f"no path: {e}")


def is_step(e: Path) -> bool:
    """One property, forwards or backwards."""
    return isinstance(e, Prop) or (isinstance(e, Inv) and isinstance(e.path, Prop))


def accepts_empty(e: Path | None) -> bool:
    """Whether the focus node itself is always an end."""
    match e:
        case IdPath() | Star() | Opt():
            return True
        case Inv(p):
            return accepts_empty(p)
        case Seq(a, b):
            return accepts_empty(a) and accepts_empty(b)
        case Alt(a, b):
            return accepts_empty(a) or accepts_empty(b)
    return False


def steps_of(e: Path | None) -> frozenset[str]:
    """The properties of a path."""
    match e:
        case Prop(n):
            return frozenset({n})
        case Inv(p) | Star(p) | Opt(p):
            return steps_of(p)
        case Seq(a, b) | Alt(a, b):
            return steps_of(a) | steps_of(b)
    return frozenset()


def path_text(e: Path) -> str:
    match e:
        case Prop(n):
            return n
        case Inv(p):
            return f"^{path_text(p)}" if isinstance(p, Prop) else f"^({path_text(p)})"
        case Seq(a, b):
            return f"{path_text(a)}/{path_text(b)}"
        case Alt(a, b):
            return f"({path_text(a)}|{path_text(b)})"
        case Star(p):
            return f"({path_text(p)})*"
        case Opt(p):
            return f"({path_text(p)})?"
    return "id"


@dataclass(frozen=True)
class Automaton:
    """States 0 (start) and one per property occurrence; state i > 0 is entered by its leaf (name, inverse)."""

    leaves: tuple[tuple[str, bool], ...]
    edges: tuple[tuple[int, int], ...]
    accepting: frozenset[int]

    @property
    def states(self) -> range:
        return range(len(self.leaves) + 1)

    def components(self) -> list[frozenset[int]]:
        """Sets of states that reach each other, in topological order."""
        after = {q: {c for b, c in self.edges if b == q} for q in self.states}
        for via in self.states:
            for q in self.states:
                if via in after[q]:
                    after[q] |= after[via]
        groups = {frozenset({q} | {r for r in after[q] if q in after[r]}) for q in self.states}
        # A group comes after all groups that reach it, and those have fewer states before them.
        before = {x: sum(1 for q in self.states if q not in x and after[q] & x) for x in groups}
        return sorted(groups, key=lambda x: (before[x], min(x)))

    def loops(self, group: frozenset[int]) -> bool:
        return any(b in group and c in group for b, c in self.edges)

    def order(self) -> list[int] | None:
        """States in topological order, or None if the automaton has a loop."""
        groups = self.components()
        return None if any(map(self.loops, groups)) else [q for x in groups for q in x]


def compile_path(e: Path) -> Automaton:
    leaves: list[tuple[str, bool]] = []
    edges: set[tuple[int, int]] = set()

    def build(x: Path) -> tuple[bool, set[int], set[int]]:
        """Whether the empty path is in, the first and the last positions."""
        match x:
            case Prop(n) | Inv(Prop(n)):
                leaves.append((n, isinstance(x, Inv)))
                return False, {len(leaves)}, {len(leaves)}
            case Seq(a, b):
                (e1, f1, l1), (e2, f2, l2) = build(a), build(b)
                edges.update((p, q) for p in l1 for q in f2)
                return e1 and e2, f1 | (f2 if e1 else set()), l2 | (l1 if e2 else set())
            case Alt(a, b):
                (e1, f1, l1), (e2, f2, l2) = build(a), build(b)
                return e1 or e2, f1 | f2, l1 | l2
            case Star(p):
                _, f, last = build(p)
                edges.update((i, j) for i in last for j in f)
                return True, f, last
            case Opt(p):
                _, f, last = build(p)
                return True, f, last
        raise TypeError(f"no path: {x}")

    empty, first, last = build(push_inverse(e))
    edges.update((0, q) for q in first)
    return Automaton(tuple(leaves), tuple(sorted(edges)), frozenset(last | ({0} if empty else set())))


def parse_path(text: str) -> Path:
    """``a/b``, ``a|b``, ``^a``, ``a*``, ``a?`` and parentheses."""
    at = 0

    def peek() -> str:
        return text[at] if at < len(text) else ""

    def alternatives() -> Path:
        nonlocal at
        out = chain()
        while peek() == "|":
            at += 1
            out = Alt(out, chain())
        return out

    def chain() -> Path:
        nonlocal at
        out = atom()
        while peek() == "/":
            at += 1
            out = Seq(out, atom())
        return out

    def atom() -> Path:
        nonlocal at
        if peek() == "^":
            at += 1
            return Inv(atom())
        if peek() == "(":
            at += 1
            out = alternatives()
            if peek() != ")":
                raise ValueError(f"missing ) at {at} in {text!r}")
            at += 1
        else:
            start = at
            while peek() and (peek().isalnum() or peek() in "_-"):
                at += 1
            if start == at:
                raise ValueError(f"a property is missing at {at} in {text!r}")
            out = Prop(text[start:at])
        while peek() and peek() in "*?":
            out = Star(out) if peek() == "*" else Opt(out)
            at += 1
        return out

    out = alternatives()
    if at != len(text):
        raise ValueError(f"cannot read {text[at:]!r}")
    return out
