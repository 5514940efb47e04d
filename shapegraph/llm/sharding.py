"""Resharding by minimum-cost flow.

Old shards are cut into blocks (ranges of a hash of the id). Block sizes, a bounded table, give each shard's bytes; a
minimum-cost flow from old sizes to new capacities decides how many bytes go from which shard to which. Whole blocks
move where they fit; only the block at a boundary is split by rows. Rows that stay keep their shard, so only shards
with a flow are rewritten.
"""

from __future__ import annotations

import heapq
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import cut, fresh_path, table


def min_cost_flow(supply: list[int], capacity: list[int], cost: list[list[int]]) -> list[list[int]]:
    """Flow from sources to sinks of least total cost, by successive shortest paths with potentials.

    All supply is placed; sum(capacity) must reach sum(supply). Zero supplies and capacities are allowed.
    """
    if sum(capacity) < sum(supply):
        raise ValueError("capacities hold less than the supplies")
    n, m = len(supply), len(capacity)
    flow = [[0] * m for _ in range(n)]
    left, room = list(supply), list(capacity)
    potential = [0] * (n + m)
    while any(left):
        distance, parent = [float("inf")] * (n + m), [-1] * (n + m)
        heap = [(0, i) for i in range(n) if left[i]]
        for _, i in heap:
            distance[i] = 0
        while heap:
            d, u = heapq.heappop(heap)
            if d > distance[u]:
                continue
            edges = [(n + j, cost[u][j]) for j in range(m)] if u < n else [(i, -cost[i][u - n]) for i in range(n) if flow[i][u - n]]
            for v, c in edges:
                new = d + c + potential[u] - potential[v]
                if new < distance[v]:
                    distance[v], parent[v] = new, u
                    heapq.heappush(heap, (new, v))
        end = min((n + j for j in range(m) if room[j]), key=lambda v: distance[v] + potential[v])
        reach = distance[end]
        potential = [p + min(d, reach) for p, d in zip(potential, distance, strict=True)]
        path = [end]
        while parent[path[-1]] >= 0:
            path.append(parent[path[-1]])
        path.reverse()
        step = min([left[path[0]], room[end - n], *(flow[v][u - n] for u, v in zip(path, path[1:], strict=False) if u >= n)])
        for u, v in zip(path, path[1:], strict=False):
            if u < n:
                flow[u][v - n] += step
            else:
                flow[v][u - n] -= step
        left[path[0]] -= step
        room[end - n] -= step
    return flow


def even_capacities(total: int, shards: int) -> list[int]:
    return [total // shards + (i < total % shards) for i in range(shards)]


def _prefix(col: str, by: list[str], order: list) -> Column:
    """Sum of ``col`` over the rows before this one."""
    return F.sum(col).over(W.partitionBy(*by).orderBy(*order).rowsBetween(W.unboundedPreceding, -1))


def reshard(df: DataFrame, shards: int = 16, old_shard: Column | None = None, id_col: str = "doc_id", text_col: str = "text", blocks: int = 1024, old_count: int = 12, out: str | None = None) -> DataFrame:
    """doc_id, size, text_crc32, old_shard, shard and a gapless slot within the shard, for every input row.

    ``old_shard`` (values 0 to old_count - 1) is where rows are now; by default a hash layout over ``old_count`` shards.
    New sizes in bytes differ by less than two rows from equal. Null texts have size 1 and the checksum of the empty
    text; rows with a null id are dealt by their texts; repeated rows get slots of their own; an empty table stays empty.

    With ``out`` the affected shards are rewritten below it: folders shard=k hold, in order of slots, the rows of every
    shard that rows leave or reach, with all columns of ``df``, slot and old_shard. Their part of the result is then read
    from those files; shards without a transfer keep theirs. Texts are shuffled once, by block.
    """
    spark = df.sparkSession
    if out is not None and {"shard", "slot", "old_shard"} & set(df.columns):
        raise ValueError("documents have a column named shard, slot or old_shard")
    raw = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    hashed = F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")), F.crc32(raw))
    old = hashed % old_count if old_shard is None else old_shard
    known = [F.col(id_col).cast("long").alias("doc_id"), (F.octet_length(raw) + 1).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"), old.cast("int").alias("old_shard"), ((hashed / old_count).cast("long") % blocks).cast("int").alias("block")]
    base = cut(df.select(*known), "shard-rows")
    # One row per (old shard, block): bounded by old_count * blocks.
    sizes = base.groupBy("old_shard", "block").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows")).orderBy("old_shard", "block").collect()
    supply = [0] * old_count
    starts = []
    for r in sizes:
        starts.append((r["old_shard"], r["block"], supply[r["old_shard"]], r["bytes"]))
        supply[r["old_shard"]] += r["bytes"]
    flow = min_cost_flow(supply, even_capacities(sum(supply), shards), [[int(i != j) for j in range(shards)] for i in range(old_count)])
    ranges = []  # of each old shard's bytes, first those that stay; a row goes where its middle is
    for i in range(old_count):
        at = 0
        for j in sorted((j for j in range(shards) if flow[i][j]), key=lambda j: (j != i, j)):
            ranges.append((i, at, at + flow[i][j], j))
            at += flow[i][j]
    offsets = F.broadcast(spark.createDataFrame(starts, "old_shard int, block int, block_start long, block_bytes long"))
    goes = F.broadcast(spark.createDataFrame(ranges, "old_shard int, low long, high long, shard int"))
    order = [F.col("doc_id").asc_nulls_first(), "text_crc32", "size"]

    def dealt(rows: DataFrame, *more: str) -> DataFrame:
        return (
            rows.join(offsets, ["old_shard", "block"])
            .withColumn("at", F.col("block_start") + F.coalesce(_prefix("size", ["old_shard", "block"], order), F.lit(0)))
            .join(goes, "old_shard")
            .where((2 * F.col("at") + F.col("size") >= 2 * F.col("low")) & (2 * F.col("at") + F.col("size") < 2 * F.col("high")))
            .withColumn("nth", F.row_number().over(W.partitionBy("old_shard", "block", "shard").orderBy("at")))
            .select("doc_id", "size", "text_crc32", "old_shard", "block", "shard", "nth", *more)
        )

    placed = cut(dealt(base), "shard-placed")
    counted = placed.groupBy("shard", "old_shard", "block").agg(F.count("*").alias("rows")).collect()  # bounded like ``sizes``
    first, filled = [], [0] * shards
    for r in sorted(counted, key=lambda r: (r["shard"], r["old_shard"], r["block"])):
        first.append((r["shard"], r["old_shard"], r["block"], filled[r["shard"]]))
        filled[r["shard"]] += r["rows"]
    first_slot = F.broadcast(spark.createDataFrame(first, "shard int, old_shard int, block int, first_slot long"))

    def slotted(rows: DataFrame) -> DataFrame:
        return rows.join(first_slot, ["shard", "old_shard", "block"]).withColumn("slot", F.col("first_slot") + F.col("nth") - 1).drop("first_slot", "nth", "block")

    plan = slotted(placed)
    touched = sorted({k for i in range(old_count) for j in range(shards) if i != j and flow[i][j] for k in (i, j)} | {k for k in range(shards, old_count) if supply[k]})
    if out is None or not touched:
        return plan
    names = [f"in_{i}" for i in range(len(df.columns))]
    whole = slotted(dealt(df.select(*known, *(F.col(f"`{c}`").alias(n) for c, n in zip(df.columns, names, strict=True))), *names)).where(F.col("shard").isin(touched))
    files = whole.select(*(F.col(n).alias(c) for c, n in zip(df.columns, names, strict=True)), "slot", "old_shard", "shard")
    files.sortWithinPartitions("shard", "slot").write.option("compression", "zstd").partitionBy("shard").parquet(out)
    written = spark.read.schema(files.schema).parquet(out)
    seen = written.select(known[0], known[1], known[2], "old_shard", "shard", "slot")
    return seen.unionByName(plan.where(~F.col("shard").isin(touched)))


def _numbered(df: DataFrame, keys: list[str], name: str) -> DataFrame:
    """Rows numbered from 1 among those with equal keys. Rows of one input partition are numbered on their own, and their
    counts, one row for each key and partition, say where each partition starts, so no key's rows meet in one task."""
    parted = cut(df.withColumn("__part", F.spark_partition_id()), "numbered")
    counts = parted.groupBy(*keys, "__part").agg(F.count("*").alias("__held"))
    before = F.coalesce(F.sum("__held").over(W.partitionBy(*keys).orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    starts = counts.withColumn("__before", before).select(*(F.col(k).alias(f"{k}__") for k in keys), F.col("__part").alias("__part__"), "__before")
    same = (F.col("__part") == F.col("__part__")) & reduce(lambda x, y: x & y, (F.col(k).eqNullSafe(F.col(f"{k}__")) for k in keys))
    nth = F.row_number().over(W.partitionBy(*keys, "__part").orderBy("__part"))
    numbered = parted.withColumn("__nth", nth).join(starts, same).withColumn(name, F.col("__nth") + F.col("__before"))
    return numbered.drop("__nth", "__part", "__part__", "__before", *(f"{k}__" for k in keys))


def rewrite(documents: DataFrame, plan: DataFrame, out: str, id_col: str = "doc_id", text_col: str = "text") -> list[int]:
    """Write the files of those shards whose rows change (rows arrive or leave) below ``out``, in folders shard=k with all
    columns of ``documents``; the shards written. Shards without a transfer keep their files.

    ``plan`` is a result of :func:`reshard` for the same documents. Rows meet their places by id (null is a value), size,
    checksum and number among equals, so null and repeated ids are written exactly as often as they are there; tables
    without rows write nothing. A column named ``shard`` raises ValueError, since the folders are named by it.
    """
    if "shard" in documents.columns:
        raise ValueError("documents have a column named shard")
    columns, names = documents.columns, [f"in_{i}" for i in range(len(documents.columns))]
    documents, id_col, text_col = documents.toDF(*names), names[columns.index(id_col)], names[columns.index(text_col)]
    touched = sorted({r[0] for r in plan.where(F.col("shard") != F.col("old_shard")).select(F.explode(F.array("shard", "old_shard"))).distinct().collect()})
    raw = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    keys = ["__id", "__size", "__crc"]
    rows = _numbered(documents.select("*", F.col(id_col).cast("long").alias("__id"), (F.octet_length(raw) + 1).cast("long").alias("__size"), F.crc32(raw).alias("__crc")), keys, "__n")
    places = _numbered(plan.select(F.col("doc_id").alias("__id"), F.col("size").alias("__size"), F.col("text_crc32").alias("__crc"), "shard"), keys, "__n")
    places = places.where(F.col("shard").isin(touched)).select(*(F.col(k).alias(f"{k}_p") for k in (*keys, "__n")), "shard")
    same = reduce(lambda x, y: x & y, (F.col(k).eqNullSafe(F.col(f"{k}_p")) for k in (*keys, "__n")))
    placed = rows.join(places, same).select(*names, "shard").toDF(*columns, "shard")
    placed.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("shard").parquet(out)
    return touched


def op10_flow_resharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The places of all documents after resharding 12 hashed shards into 16 of near equal bytes, read from the new files."""
    plan = reshard(table(spark, sf_dir, "documents"), out=fresh_path(spark, "shards"))
    return plan.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "old_shard")
