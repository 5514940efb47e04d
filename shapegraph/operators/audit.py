"""Audits of evidence subgraphs; each returns rows that should not be."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shapes import Shape, ShapeSchema, is_monotone
from ..sources.graph import TripleGraph, cut
from .evidence import Engine


def audit_sufficiency(g: TripleGraph, shapes: list[Shape], schema: ShapeSchema | None = None) -> DataFrame:
    """request, v: nodes that satisfy a request in the graph but not in its evidence subgraph."""
    whole = Engine(g, schema)
    small = Engine(TripleGraph.of(cut(whole.subgraph(*shapes), "audit"), sorted(g.parts), g.vocabulary), schema)
    found = []
    for i, s in enumerate(shapes):
        judged = small.judged(s, s, cut(whole.resolve(s), "audit"))
        found.append(judged.where("not ok").select(F.lit(i).alias("request"), "v"))
    return reduce(DataFrame.unionAll, found)


def audit_schema(g: TripleGraph, schema: ShapeSchema) -> DataFrame:
    """The report on the schema subgraph of a conforming graph; targets must be monotone."""
    if not all(is_monotone(d.target) for d in schema.defs):
        raise ValueError("a target is not monotone")
    return Engine(TripleGraph.of(cut(Engine(g, schema).schema_subgraph(), "audit"), sorted(g.parts), g.vocabulary), schema).report()


def audit_subgraph(g: TripleGraph, found: DataFrame) -> DataFrame:
    return found.join(g.triples(), ["s", "p", "o"], "left_anti")


def compare_graphs(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: triples only in a, only in b, and whether both are equal."""
    one = a.select("s", "p", "o", F.lit(1).alias("a"), F.lit(0).alias("b")).unionAll(b.select("s", "p", "o", F.lit(0), F.lit(1)))
    sides = one.groupBy("s", "p", "o").agg(F.max("a").alias("a"), F.max("b").alias("b"))
    counts = sides.agg(F.coalesce(F.sum(F.col("a") - F.col("a") * F.col("b")), F.lit(0)).alias("missing"), F.coalesce(F.sum(F.col("b") - F.col("a") * F.col("b")), F.lit(0)).alias("extra"))
    return counts.withColumn("equal", (F.col("missing") == 0) & (F.col("extra") == 0))
