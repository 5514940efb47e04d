"""Connected components of edge tables that grow with the data."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def components(edges: DataFrame, nodes: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Smallest node of each connected component: columns node, root.

    Alternates hooking of roots (each root to the least neighbouring root) with pointer jumping, so long chains take
    logarithmically many rounds; each round is cut to the shared folder. Edges hold columns a, b; loops and repeats do
    no harm. Raises if ``most_rounds`` do not suffice.
    """
    both = cut(edges.where("a <> b").select("a", "b").union(edges.where("a <> b").select(F.col("b"), F.col("a"))).distinct(), "edges")
    labels = cut(nodes.select("node").union(both.select("a")).distinct().select("node", F.col("node").alias("root")), "labels")
    if both.isEmpty():
        return labels
    for _ in range(most_rounds):
        ends = labels.select(F.col("node").alias("b"), F.col("root").alias("other"))
        near = both.join(ends, "b").groupBy(F.col("a").alias("node")).agg(F.min("other").alias("least"))
        hooked = labels.join(near, "node", "left").withColumn("least", F.least("root", F.coalesce("least", "root")))
        # Each root takes the least that any of its members saw, then members take their root's new root.
        moved = hooked.groupBy("root").agg(F.min("least").alias("to"))
        jump = moved.select(F.col("root").alias("to"), F.col("to").alias("further"))
        moved = moved.join(jump, "to", "left").select("root", F.least("to", F.coalesce("further", "to")).alias("to"))
        new = cut(labels.join(moved, "root").select("node", F.col("to").alias("root"), (F.col("to") < F.col("root")).alias("changed")), "labels")
        labels = new.select("node", "root")
        if new.where("changed").isEmpty():
            return labels
    raise RuntimeError("components did not settle")
