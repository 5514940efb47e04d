"""Fused validation and extraction of star shapes: one grouping by subject gives verdicts and evidence rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.paths import Prop
from ..plans.shapes import AtLeast, AtMost, ForAll, Shape, conjuncts, holds, is_local, negate, to_nnf
from ..sources.graph import TripleGraph


def is_star(s: Shape) -> bool:
    """Quantifiers over single properties whose inner shapes the end alone decides."""
    return all(isinstance(c, AtLeast | AtMost | ForAll) and isinstance(c.path, Prop) and is_local(c.shape) for c in conjuncts(to_nnf(s)))


def star_window(g: TripleGraph, s: Shape, target: DataFrame) -> DataFrame:
    """v, ok, s, p, o, evidence for every target node: its rows of the shape's properties with the node's verdict and
    whether the row is evidence. Nodes without such rows have one row with null triple."""
    parts = conjuncts(to_nnf(s))
    props = sorted({c.path.name for c in parts})  # type: ignore[union-attr]
    rows = target.join(g.triples(props).withColumnRenamed("s", "v"), "v", "left")
    same, ok, shown = W.partitionBy("v"), [], []
    for c in parts:
        own = F.col("p") == c.path.name  # type: ignore[union-attr]
        good = F.coalesce(own & holds(c.shape, F.col("o")), F.lit(False))  # type: ignore[union-attr]
        bad = F.coalesce(own & holds(negate(c.shape), F.col("o")), F.lit(False))  # type: ignore[union-attr]
        if isinstance(c, AtLeast):
            ok.append(F.sum(good.cast("int")).over(same) >= c.n)
            shown.append(good)
        elif isinstance(c, AtMost):
            ok.append(F.sum(good.cast("int")).over(same) <= c.n)
            shown.append(bad)
        else:
            ok.append(F.sum(bad.cast("int")).over(same) == 0)
            shown.append(F.coalesce(own, F.lit(False)))
    verdict, evidence = reduce(lambda a, b: a & b, ok), reduce(lambda a, b: a | b, shown)
    return rows.select("v", verdict.alias("ok"), F.col("v").alias("s"), "p", "o", evidence.alias("evidence"))


def validate_and_extract_star(g: TripleGraph, s: Shape, target: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Violating nodes (v) and evidence triples of the conforming ones, from one window."""
    seen = star_window(g, s, target)
    return seen.where("not ok").select("v").distinct(), seen.where("ok and evidence").select("s", "p", "o")
