"""The measures named as arguments (all without any) at $BENCH_SF_DIR; a JSON line for each shape, pattern or curve."""

import json
import os
import sys

from pyspark.sql import SparkSession

from shapegraph.measures import classify_growth, overhead, result_bytes, scaling_curve, slice_curve, translation_vs_fused
from shapegraph.plans.patterns import bindings, pattern_images
from shapegraph.sources.graph import TripleGraph
from shapegraph.sources.mapping import build_graph
from shapegraph.workloads import PATTERNS, SLICES, contains_slice, hub, hub_request, profile_shapes, segments


def show(**measured: object) -> None:
    print(json.dumps(measured), flush=True)


def growth(g: TripleGraph, runs: int, sf_dir: str) -> None:
    shapes, parts = profile_shapes(), [segments(g, k) for k in range(1, 6)]
    for name in ("B-addr", "B-hours", "B-offer", "B-LineItem-card"):
        curve = scaling_curve(parts, *shapes[name], runs=runs)
        show(measure="growth", shape=name, seconds=curve, growth=classify_growth(curve))


def slices(g: TripleGraph, runs: int, sf_dir: str) -> None:
    request = hub_request(hub(sf_dir, g.spark))
    show(measure="slices", seconds=slice_curve({x: contains_slice(g, x) for x in SLICES}, request, runs))


def sizes(g: TripleGraph, runs: int, sf_dir: str) -> None:
    for name in ("A4a", "A4b"):
        show(measure="result_size", pattern=name, bindings=result_bytes(bindings(g, PATTERNS[name])), subgraph=result_bytes(pattern_images(g, PATTERNS[name])))


def overheads(g: TripleGraph, runs: int, sf_dir: str) -> None:
    """All shapes, those with ``closed`` last since they read every property; each is shown when it is measured."""
    each: dict[str, float] = {}
    for name, shape in sorted(profile_shapes().items(), key=lambda x: x[0].endswith("-neg")):
        each |= overhead(g, {name: shape}, runs)
        show(measure="overhead_percent", shape=name, percent=each[name], shapes=len(each), mean=sum(each.values()) / len(each))


def translations(g: TripleGraph, runs: int, sf_dir: str) -> None:
    shapes = profile_shapes()
    for name in ("B-Order-card", "B-hours", "B-addr"):
        show(measure="translation_vs_fused", shape=name, seconds=translation_vs_fused(g, *shapes[name], runs=runs))


MEASURES = {"translation": translations, "slices": slices, "sizes": sizes, "overhead": overheads, "growth": growth}


def main(names: list[str]) -> None:
    sf_dir, cpus, runs = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8"), int(os.environ.get("RUNS", "5"))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    g = build_graph(spark, sf_dir).cached()
    for name in names or MEASURES:
        MEASURES[name](g, runs, sf_dir)
    spark.stop()


if __name__ == "__main__":
    main(sys.argv[1:])
