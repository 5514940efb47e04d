"""Path reach and traces over position automata.

Node sets per automaton state, never enumerated paths. ``keys`` is ["v"] when results carry their focus node and []
when only the union counts; without it sets stay linear in the graph. States outside loops unroll into one plan. A loop
over vocabulary (subclass links) becomes one join with its closure, computed once within a size bound; any other loop runs
semi-naive rounds, held by the driver while they are few and else each cut to the shared folder.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.paths import Alt, Automaton, IdPath, Inv, Path, Prop, Seq, Star, compile_path, is_step
from ..sources.graph import TripleGraph, cut, local

MOST_ROUNDS = 10_000
#: Rounds after which what was seen is written together, so that a round reads few files.
COMPACT = 8
#: Most new nodes of a round that the driver holds, while it holds at most ``MOST_CLOSURE`` in all.
FEW = 1_000
#: Paths of more leaves write the edges that were walked once, since the way back reads each several times.
MOST_UNROLLED = 3
#: Most constants that become a list in a filter, which reaches the scan.
MOST_LISTED = 1_000
#: Most rows of a closure that is broadcast.
MOST_CLOSURE = 200_000


def _step(g: TripleGraph, leaf: tuple[str, bool]) -> DataFrame:
    """Columns tail, head of one automaton leaf; rows may repeat."""
    t = g.raw(leaf[0])
    tail, head = ("o", "s") if leaf[1] else ("s", "o")
    return t.select(F.col(tail).alias("tail"), F.col(head).alias("head"))


def _closure(g: TripleGraph, a: Automaton, inner: list[tuple[int, int]], backward: bool) -> DataFrame | None:
    """q, x, r, y: all that one or more steps inside a loop reach, if the loop's properties are vocabulary and the closure
    has ``MOST_CLOSURE`` rows at most; else None."""
    onward: dict[tuple[int, str], set[tuple[int, str]]] = {}
    for b, c in inner:
        name, inverse = a.leaves[(b if backward else c) - 1]
        rows = g.vocabulary_rows(name)
        if rows is None:
            return None
        for s, o in rows:
            x, y = (o, s) if inverse != backward else (s, o)
            onward.setdefault((b, x), set()).add((c, y))
    found = []
    for first in onward:
        seen: set[tuple[int, str]] = set()
        frontier = {first}
        while frontier:
            frontier = set().union(*(onward.get(n, set()) for n in frontier)) - seen
            seen |= frontier
        found += [(*first, *n) for n in seen]
        if len(found) > MOST_CLOSURE:
            return None
    return local(g.spark, found, q=pa.int32(), x=pa.string(), r=pa.int32(), y=pa.string())


Walks = dict[tuple[int, int], DataFrame]


def _levels(g: TripleGraph, a: Automaton, start: dict[int, DataFrame | None], keys: list[str], backward: bool = False, walks: Walks | None = None) -> dict[int, DataFrame]:
    """Nodes (column x, beside the keys) of every state, from the start sets along the automaton (or against it).

    Against it, ``walks`` (keys, tail, head of each edge, from an earlier pass along it) are all that may be walked: an end
    that many nodes share, such as a flag, then leads back only to nodes of its own focus. A start of None is every node: its
    steps are read whole, and the state has no set of its own."""
    walks = dict(walks) if walks is not None else None

    def onward(frontier: DataFrame | None, source: int, target: int) -> DataFrame:
        if frontier is None:
            step = _step(g, a.leaves[target - 1])
            return step.select(*(F.col("tail").alias(k) for k in keys), F.col("head").alias("x")).distinct()
        if walks is not None:
            walked = walks[target, source].join(frontier.withColumnRenamed("x", "head"), [*keys, "head"], "left_semi")
            return walked.select(*keys, F.col("tail").alias("x")).distinct()
        step = _step(g, a.leaves[(source if backward else target) - 1])
        near, far = ("head", "tail") if backward else ("tail", "head")
        return frontier.join(step, frontier["x"] == step[near]).select(*keys, F.col(far).alias("x")).distinct()

    moves = [(c, b) for b, c in a.edges if walks is None or (b, c) in walks] if backward else list(a.edges)
    groups = a.components()
    columns = ["q", *keys, "x"]
    levels: dict[int, DataFrame | None] = {}
    for group in reversed(groups) if backward else groups:
        entered: dict[int, DataFrame] = {}
        for q in group:
            if q in start and start[q] is None:
                levels[q] = None
                continue
            sets = [start[q]] if q in start else []
            sets += [onward(levels[b], b, c) for b, c in moves if c == q and b not in group and b in levels]
            if sets:
                entered[q] = reduce(DataFrame.unionAll, sets).distinct() if len(sets) > 1 else sets[0]
        if not entered or not a.loops(group):
            levels |= entered
            continue
        inner = [(b, c) for b, c in moves if b in group and c in group]
        entry = reduce(DataFrame.unionAll, [d.withColumn("q", F.lit(q)).select(*columns) for q, d in entered.items()])
        closure = _closure(g, a, inner, backward)
        if closure is not None:
            reached = entry.join(F.broadcast(closure), ["q", "x"]).select(F.col("r").alias("q"), *keys, F.col("y").alias("x"))
            seen = entry.unionAll(reached).distinct()
        else:
            if walks is not None:
                walks |= {(b, c): cut(walks[b, c], "walks") for c, b in inner}
            seen = _rounds(entry, inner, onward, columns)
        levels |= {q: seen.where(F.col("q") == q).drop("q") for q in group}
    return levels


def _rounds(entry: DataFrame, inner: list[tuple[int, int]], onward: Callable[[DataFrame, int, int], DataFrame], columns: list[str]) -> DataFrame:
    """Semi-naive rounds inside a loop until a round finds nothing new. While few nodes are new, the driver holds them and what
    was seen; from the first round that is larger they are written."""
    spark, types = entry.sparkSession, {c: pa.int32() if c == "q" else pa.string() for c in columns}
    seen = frontier = cut(entry.distinct(), "reach")
    new = {tuple(r) for r in frontier.limit(FEW + 1).collect()}
    known, held = set(new), len(new) <= FEW
    for turn in range(MOST_ROUNDS):
        moves = [(b, c) for b, c in inner if not held or any(r[0] == b for r in new)]
        starts = {b: local(spark, sorted(r for r in new if r[0] == b), **types) if held else frontier.where(F.col("q") == b) for b, _ in moves}
        if not moves:
            return local(spark, sorted(known), **types)
        found = reduce(DataFrame.unionAll, [onward(starts[b], b, c).withColumn("q", F.lit(c)).select(*columns) for b, c in moves])
        if held:
            rows = {tuple(r) for r in found.limit(MOST_CLOSURE + 1).collect()}
            if len(rows) <= MOST_CLOSURE:
                new = rows - known
                known |= new
            held = len(rows) <= MOST_CLOSURE and len(new) <= FEW and len(known) <= MOST_CLOSURE
            if not held:
                seen, frontier = (cut(local(spark, sorted(x), **types), "reach") for x in (known, new))
            continue
        frontier = cut(found.distinct().join(seen, columns, "left_anti"), "reach")
        if frontier.isEmpty():
            return seen
        seen = seen.unionAll(frontier)
        if turn % COMPACT == COMPACT - 1:
            seen = cut(seen, "reach")
    raise RuntimeError(f"reach did not end within {MOST_ROUNDS} rounds")


def tag_ranges(g: TripleGraph, e: Path, tag: Callable[[Column], Column]) -> tuple[Automaton, dict[int, DataFrame]] | None:
    """Of a path without loops that is never empty: per state x, tag and the least and greatest end (lo, hi) with that tag that
    lead on from x. One grouping per step, so ends are never paired with focus nodes. None for other paths."""
    a = compile_path(e)
    order = a.order()
    if order is None or 0 in a.accepting:
        return None
    ranges: dict[int, DataFrame] = {}
    for q in reversed(order):
        sides = []
        if q in a.accepting:
            stop = _step(g, a.leaves[q - 1]).select(F.col("head").alias("x")).distinct()
            sides.append(stop.select("x", tag(F.col("x")).alias("tag"), F.col("x").alias("lo"), F.col("x").alias("hi")).where("tag <> ''"))
        for b, c in a.edges:
            if b == q:
                step = _step(g, a.leaves[c - 1])
                sides.append(step.join(ranges[c].withColumnRenamed("x", "head"), "head").select(F.col("tail").alias("x"), "tag", "lo", "hi"))
        if sides:
            ranges[q] = reduce(DataFrame.unionAll, sides).groupBy("x", "tag").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    return a, ranges


def trace_tags(g: TripleGraph, a: Automaton, ranges: dict[int, DataFrame], start: DataFrame) -> DataFrame:
    """s, p, o: triples on paths from start (x, tag) to ends of that tag, along the states of ``tag_ranges``."""
    ahead, found = {0: start}, []
    for q in a.order() or []:
        if q:
            into = [rows.select(F.col("head").alias("x"), "tag") for c, rows in found if c == q]
            if not into:
                continue
            ahead[q] = reduce(DataFrame.unionAll, into).distinct()
        for b, c in a.edges:
            if b == q:
                step = _step(g, a.leaves[c - 1]).join(ahead[q].withColumnRenamed("x", "tail"), "tail")
                found.append((c, step.join(ranges[c].select(F.col("x").alias("head"), "tag"), ["head", "tag"], "left_semi")))
    out = []
    for c, rows in found:
        name, inverse = a.leaves[c - 1]
        out.append(rows.select(F.col("head" if inverse else "tail").alias("s"), F.lit(name).alias("p"), F.col("tail" if inverse else "head").alias("o")))
    return _union(out, g.triples([]))


def _union(frames: list[DataFrame], empty: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionAll, frames).distinct() if frames else empty.limit(0)


def pairs(g: TripleGraph, e: Path, v: DataFrame | None) -> DataFrame:
    """Columns v, x: ends of the path from each focus node, or from every node if v is None and the path is not empty; the
    empty path yields the node itself."""
    if v is None:
        a = compile_path(e)
        if 0 in a.accepting:
            raise ValueError("a path that may be empty needs its focus nodes")
        levels = _levels(g, a, {0: None}, ["v"])
        return _union([levels[q] for q in a.accepting if levels.get(q) is not None], local(g.spark, [], v=pa.string(), x=pa.string()))
    start = v.select("v", F.col("v").alias("x"))
    if isinstance(e, IdPath):
        return start
    a = compile_path(e)
    levels = _levels(g, a, {0: start}, ["v"])
    return _union([levels[q] for q in a.accepting if q in levels], start)


def ends(g: TripleGraph, e: Path, v: DataFrame) -> DataFrame:
    """Column v: all nodes that the path reaches from any of the nodes."""
    a = compile_path(e)
    levels = _levels(g, a, {0: v.select(F.col("v").alias("x"))}, [])
    return _union([levels[q] for q in a.accepting if q in levels], v.select(F.col("v").alias("x"))).select(F.col("x").alias("v"))


def above(g: TripleGraph, e: Path, c: str) -> tuple[str, str, list[str]] | None:
    """For a step (property p) and then any number of vocabulary links q: p, q and the nodes from which links lead to c."""
    match e:
        case Seq(Prop(p), Star(Prop(q))):
            rows = g.vocabulary_rows(q)
            if rows is None:
                return None
            below: dict[str, list[str]] = {}
            for s, o in rows:
                below.setdefault(o, []).append(s)
            seen, frontier = {c}, [c]
            while frontier:
                frontier = [s for o in frontier for s in below.get(o, ()) if s not in seen]
                seen |= set(frontier)
            return (p, q, sorted(seen)) if len(seen) <= MOST_LISTED else None
    return None


def sources_of(g: TripleGraph, e: Path, x: DataFrame | str, kinds: frozenset[str] | None = None) -> DataFrame:
    """Column v: all nodes from which the path reaches one of the nodes (column v), or the one node; rows may repeat. Set
    reach against the automaton; a constant behind vocabulary links becomes a list in the scan's filter. ``kinds``: of the
    only nodes that are asked for; others may be left out."""
    if isinstance(x, str):
        if is_step(e):
            name, near, far = (e.path.name, "o", "s") if isinstance(e, Inv) else (e.name, "s", "o")  # type: ignore[attr-defined]
            own = g if kinds is None or isinstance(e, Inv) else g.about(kinds)
            return own.raw(name).where(F.col(far) == x).select(F.col(near).alias("v"))
        found = above(g, e, x)
        if found is not None:
            own = g if kinds is None else g.about(kinds)
            return own.raw(found[0]).where(F.col("o").isin(found[2])).select(F.col("s").alias("v"))
        x = local(g.spark, [(x,)], v=pa.string())
    a = compile_path(e)
    stop = x.select(F.col("v").alias("x"))
    levels = _levels(g, a, dict.fromkeys(a.accepting, stop), [], backward=True)
    return (levels[0] if 0 in levels else stop.limit(0)).select(F.col("x").alias("v"))


def sources_where(g: TripleGraph, e: Path, good: Callable[[Column], Column]) -> DataFrame:
    """Column v: all nodes from which the path, which is never empty, reaches an end that passes the condition."""
    a = compile_path(e)
    stops = {q: _step(g, a.leaves[q - 1]).where(good(F.col("head"))).select(F.col("head").alias("x")).distinct() for q in a.accepting}
    levels = _levels(g, a, stops, [], backward=True)
    return levels[0].select(F.col("x").alias("v"))


def class_trace(g: TripleGraph, e: Path, v: DataFrame, c: str, kinds: frozenset[str] | None = None) -> DataFrame | None:
    """Triples on paths from v, whose nodes are of the kinds, to c over one step and vocabulary links: the step's rows, and
    the links above each of their ends, which the driver knows. None for other paths."""
    found = above(g, e, c)
    if found is None:
        return None
    p, q, below = found
    rows, known = g.vocabulary_rows(q) or [], set(below)
    links_above: dict[str, set[tuple[str, str]]] = {}
    for start in below:
        links: set[tuple[str, str]] = set()
        frontier = {start}
        while frontier:
            fresh = {(s, o) for s, o in rows if s in frontier and o in known} - links
            links |= fresh
            frontier = {o for _, o in fresh}
        links_above[start] = links
    own = g if kinds is None else g.about(kinds)
    walked = own.raw(p).where(F.col("o").isin(below)).join(v.select(F.col("v").alias("s")), "s", "left_semi").select("s", F.lit(p).alias("p"), "o")
    pieces = [(start, s, o) for start, links in links_above.items() for s, o in links]
    if not pieces:
        return walked
    if len(pieces) > MOST_CLOSURE:
        return None
    links_of = local(g.spark, pieces, start=pa.string(), s=pa.string(), o=pa.string())
    seen = walked.select(F.col("o").alias("start")).distinct()
    return walked.unionAll(links_of.join(seen, "start", "left_semi").select("s", F.lit(q).alias("p"), "o").distinct())


def trace(g: TripleGraph, e: Path, start: DataFrame, stop: DataFrame, keys: list[str]) -> DataFrame:
    """Triples on paths of ``e`` from start to stop nodes (column x, beside the keys): s, p, o beside the keys."""
    a = compile_path(e)
    ahead = _levels(g, a, {0: start}, keys)
    walks: Walks = {}
    for b, c in a.edges:
        if b in ahead:
            walked = _step(g, a.leaves[c - 1]).join(ahead[b].withColumnRenamed("x", "tail"), "tail", "inner" if keys else "left_semi").select(*keys, "tail", "head")
            walks[b, c] = cut(walked, "walks") if len(a.leaves) > MOST_UNROLLED else walked
    back = _levels(g, a, dict.fromkeys(a.accepting, stop), keys, backward=True, walks=walks)
    found = []
    for (b, c), walked in walks.items():
        if c in back:
            name, inverse = a.leaves[c - 1]
            rows = walked.join(back[c].withColumnRenamed("x", "head"), [*keys, "head"], "left_semi")
            found.append(rows.select(*keys, F.col("head" if inverse else "tail").alias("s"), F.lit(name).alias("p"), F.col("tail" if inverse else "head").alias("o")))
    empty = g.triples([]).select(*(F.col("s").alias(k) for k in keys), "s", "p", "o")
    return _union(found, empty)


def trace_sets(g: TripleGraph, e: Path, v: DataFrame, x: DataFrame) -> DataFrame:
    """Triples on paths from any node of v to any node of x (both column v)."""
    return trace(g, e, v.select(F.col("v").alias("x")), x.select(F.col("v").alias("x")), [])


def trace_pairs(g: TripleGraph, e: Path, vx: DataFrame) -> DataFrame:
    """v, s, p, o: triples on paths from each v to its own ends x."""
    return trace(g, e, vx.select("v", F.col("v").alias("x")).distinct(), vx.select("v", "x"), ["v"])


def trace_from(g: TripleGraph, e: Path, v: DataFrame) -> DataFrame:
    return trace_pairs(g, e, pairs(g, e, v))


__all__ = ["Alt", "above", "class_trace", "ends", "pairs", "sources_of", "sources_where", "tag_ranges", "trace", "trace_from", "trace_pairs", "trace_sets", "trace_tags"]
