"""Cost and accuracy measures of the experiments; times are wall-clock seconds of full evaluation."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.evidence import Engine
from .plans.paths import steps_of
from .plans.patterns import triple_pattern
from .plans.shapes import Closed, Compare, Disj, Eq, Shape, ShapeDef, ShapeSchema, all_of, class_target, reduce_tests, simplify
from .plans.sqlgen import closures, run_sql, sql_subgraph
from .sources.graph import TripleGraph, fresh_path


def seconds(run: Callable[[], object], runs: int = 5) -> float:
    """Mean time of ``runs`` evaluations after one that is not counted."""
    run()
    start = time.perf_counter()
    for _ in range(runs):
        run()
    return (time.perf_counter() - start) / runs


def _sink(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def plain(g: TripleGraph, klass: str, s: Shape) -> DataFrame:
    """Validation alone: the target nodes that break the shape."""
    return Engine(g, ShapeSchema([ShapeDef("S", s, class_target(klass))])).report()


def fused(g: TripleGraph, klass: str, s: Shape) -> tuple[DataFrame, DataFrame]:
    """Validation with extraction: the report and the subgraph."""
    return Engine(g, ShapeSchema([ShapeDef("S", s, class_target(klass))])).validate_and_extract()


def _fuse(g: TripleGraph, klass: str, s: Shape) -> None:
    report, found = fused(g, klass, s)
    _sink(report)
    _sink(found)


def overhead(g: TripleGraph, shapes: dict[str, tuple[str, Shape]], runs: int = 5) -> dict[str, float]:
    """Extraction over plain validation in percent, for every shape; the graph should be written before."""
    out = {}
    for name, (klass, s) in shapes.items():
        alone = seconds(lambda s=s, k=klass: _sink(plain(g, k, s)), runs)
        both = seconds(lambda s=s, k=klass: _fuse(g, k, s), runs)
        out[name] = 100 * (both - alone) / alone
    return out


def scaling_curve(graphs: list[TripleGraph], klass: str, s: Shape, runs: int = 5) -> list[float]:
    """Seconds of validation with extraction over each of the growing graphs."""
    return [seconds(lambda g=g: _fuse(g, klass, s), runs) for g in graphs]


def translation_vs_fused(g: TripleGraph, klass: str, s: Shape, runs: int = 5) -> dict[str, float]:
    """Seconds of the generated SQL text and of the fused engine for a shape whose node tests are reduced away; writing the
    graph's views is loading and not part of them."""
    reduced = simplify(reduce_tests(s))
    request = all_of(reduced, class_target(klass))
    g = g.restrict(properties_of(request)).cached()
    text = sql_subgraph([request], closure=closures(g.restrict(["subClassOf"])))
    translated = run_sql(g, text)
    return {"translated": seconds(lambda: _sink(translated), runs), "fused": seconds(lambda: _fuse(g, klass, reduced), runs)}


def properties_of(s: Shape, known: set[str] | frozenset[str] = frozenset()) -> set[str]:
    """Properties that decide a shape; ``closed`` asks for all that are known beside its own."""
    out = set(steps_of(getattr(s, "path", None)))
    if isinstance(s, Eq | Disj | Compare):
        out.add(s.prop)
    if isinstance(s, Closed):
        out |= set(known) - s.props
    for inner in ("left", "right", "shape"):
        if hasattr(s, inner):
            out |= properties_of(getattr(s, inner), known)
    return out


def slice_curve(slices: dict[str, TripleGraph], request: Shape, runs: int = 1) -> dict[str, float]:
    """Seconds of one request over each slice."""
    return {name: seconds(lambda g=g: _sink(Engine(g).subgraph(request)), runs) for name, g in slices.items()}


def result_bytes(df: DataFrame) -> dict[str, int]:
    """Rows of a result and bytes of its Parquet files."""
    spark, path = df.sparkSession, fresh_path(df.sparkSession, "result")
    df.write.parquet(path)
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    size = folder.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(folder).getLength()
    return {"rows": spark.read.parquet(path).count(), "bytes": size}


def redundant_triples(g: TripleGraph, s: Shape, node: str, most: int = 50) -> list[tuple[str, str, str]]:
    """Evidence triples of a node without any one of which the node still conforms; for evidence of ``most`` triples at
    most, since every triple costs an evaluation (larger evidence raises an error)."""
    rows = [tuple(r) for r in Engine(g).evidence_of(s, node).select("s", "p", "o").limit(most + 1).collect()]
    if len(rows) > most:
        raise ValueError(f"more than {most} triples of evidence")
    spare = []
    for gone in rows:
        left = [r for r in rows if r != gone]
        engine = Engine(TripleGraph.from_rows(g.spark, left) if left else TripleGraph(g.spark, {}))
        if not engine.conform(s, engine.node_set([node])).isEmpty():
            spare.append(gone)
    return sorted(spare)


def classify_growth(times: list[float]) -> str:
    """By the last over the first segment: constant below 1.1, modest below 1.5, else linear."""
    ratio = times[-1] / times[0]
    return "constant" if ratio < 1.1 else "modest" if ratio < 1.5 else "linear"


def shares(found: DataFrame, nodes: DataFrame, g: TripleGraph, prop: str) -> DataFrame:
    """One row: nodes reached and their share of all objects of the property, triples and their share of its triples."""
    whole = g.prop(prop)
    return (
        nodes.agg(F.count("*").alias("nodes"))
        .crossJoin(found.agg(F.count("*").alias("triples")))  # both are one row
        .crossJoin(whole.agg(F.count_distinct("o").alias("all_nodes"), F.count("*").alias("all_triples")))
        .withColumn("node_share", F.round(F.col("nodes") / F.col("all_nodes"), 6))
        .withColumn("triple_share", F.round(F.col("triples") / F.col("all_triples"), 6))
    )


def emulate_by_patterns(g: TripleGraph, s: Shape) -> tuple[DataFrame, int]:
    """The triples that single-pattern requests fetch to decide the shape, and the number of requests."""
    named = sorted(properties_of(s, set(g.parts)))
    if not named:
        return g.triples([]), 0
    out = triple_pattern(g, p=named[0])
    for p in named[1:]:
        out = out.unionAll(triple_pattern(g, p=p))
    return out, len(named)


__all__ = ["classify_growth", "emulate_by_patterns", "overhead", "seconds", "shares"]
