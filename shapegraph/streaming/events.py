"""Replayed ``events`` as a stream: windows, duplicates, and star shapes kept up to date for touched subjects only."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.terms import decimal, iri
from ..operators.star import star_window
from ..plans.shapes import Shape
from ..sources.graph import TRIPLES, TripleGraph, fresh_path

#: How late a row may come before its windows and its duplicates' memory are closed.
LATENESS = "1 hour"


def stream_table(spark: SparkSession, sf_dir: str, name: str, files_per_batch: int = 1000) -> DataFrame:
    """A table's files as a stream, so many of them in a micro-batch."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    # As a pattern, since a stream takes a plain path for a folder, and a table may be one file.
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf_dir}/{name}[.]parquet")


def timed(events: DataFrame, ts: str = "ts") -> DataFrame:
    """Event time as an instant (rows without one cannot be placed and go), with the watermark."""
    return events.withColumn(ts, F.col(ts).cast("timestamp")).where(F.col(ts).isNotNull()).withWatermark(ts, LATENESS)


def once_each(events: DataFrame, *keys: str) -> DataFrame:
    """Rows without repeats of a key within the watermark; state is dropped as time passes."""
    return timed(events).dropDuplicatesWithinWatermark(list(keys))


def window_counts(events: DataFrame, window: Column, *keys: str) -> DataFrame:
    """Rows per window and key; ``window`` is ``F.window`` (tumbling or sliding) or ``F.session_window`` over ``ts``."""
    return timed(events).groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n")


def drain(stream: DataFrame, tag: str, mode: str = "append") -> DataFrame:
    """All that is there now, in as many micro-batches as it takes, into one folder per batch of the shared folder.

    ``complete`` keeps the last state; other modes keep every batch. A batch that is run again replaces its folder.
    """
    spark, base = stream.sparkSession, fresh_path(stream.sparkSession, tag)

    def store(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows" if mode == "complete" else f"{base}/rows/batch={number}")

    run = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/progress").trigger(availableNow=True).foreachBatch(store).start()
    run.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/rows")


def event_triples(events: DataFrame) -> DataFrame:
    """s, p, o of each event's user and value."""
    s = iri("event", "event_id")
    pairs = F.array(F.struct(F.lit("byUser").alias("p"), iri("user", "user_id").alias("o")), F.struct(F.lit("value").alias("p"), decimal(F.col("value")).alias("o")))
    return events.select(s.alias("s"), F.explode(pairs).alias("t")).select("s", "t.p", "t.o").where("s is not null and o is not null")


def keep_star(triples: DataFrame, shape: Shape, properties: Iterable[str], tag: str = "star") -> DataFrame:
    """v, ok, s, p, o, evidence of a star shape after a stream of triples, for every subject that it named.

    Each micro-batch adds its triples to the store and judges the subjects that it touches anew; the last judgement of
    a subject counts. So shapes need not be monotone, and untouched subjects cost nothing but the scan of the store.
    """
    spark, base, properties = triples.sparkSession, fresh_path(triples.sparkSession, tag), list(properties)

    def judge(batch: DataFrame, number: int) -> None:
        batch.select("s", "p", "o").write.mode("overwrite").parquet(f"{base}/triples/batch={number}")
        touched = spark.read.schema(TRIPLES).parquet(f"{base}/triples/batch={number}").select(F.col("s").alias("v")).distinct()
        stored = spark.read.schema(TRIPLES + ", batch long").parquet(f"{base}/triples").where(F.col("batch") <= number)
        g = TripleGraph.of(stored.join(touched, F.col("s") == F.col("v"), "left_semi"), properties)
        star_window(g, shape, touched).write.mode("overwrite").parquet(f"{base}/judged/batch={number}")

    run = triples.writeStream.option("checkpointLocation", f"{base}/progress").trigger(availableNow=True).foreachBatch(judge).start()
    run.awaitTermination()
    judged = spark.read.schema("v string, ok boolean, s string, p string, o string, evidence boolean, batch long").parquet(f"{base}/judged")
    return judged.withColumn("last", F.max("batch").over(W.partitionBy("v"))).where("batch = last").drop("batch", "last")
