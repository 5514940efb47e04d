"""Shared plumbing: documents in, lineage cuts in the cluster's shared folder, bounded text slices."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one numpy step works on; bounds a Python worker's memory whatever the batch holds.
SLICE_BYTES = 1 << 20

_own_dir: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The two columns an operator works on, as ``doc_id`` and ``text``; other columns cannot clash with its own."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a temporary folder only where it is unset (single-machine tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not _own_dir:
        _own_dir.append(tempfile.mkdtemp(prefix="shapegraph-"))
        atexit.register(shutil.rmtree, _own_dir[0], True)
    return f"file://{_own_dir[0]}"


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def cut(df: DataFrame, tag: str) -> DataFrame:
    """Write to the shared folder and reread: survives lost executors and is computed once."""
    path = fresh_path(df.sparkSession, tag)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release() -> None:
    """Give freed memory back: reused workers stand idle beside the next stage."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def slices(batches: Iterable[pa.RecordBatch], text_col: str = "text", most: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Runs of rows with about ``most`` bytes of text (one row at least) and their UTF-8 texts, null as empty."""
    release()
    for batch in batches:
        texts = batch.column(batch.schema.get_field_index(text_col))
        column = texts.cast(pa.large_binary() if pa.types.is_large_string(texts.type) else pa.binary())
        start, held = 0, []
        total = 0
        for i, value in enumerate(column):
            raw = value.as_py() or b""
            held.append(raw)
            total += len(raw)
            if total >= most:
                yield batch.slice(start, i + 1 - start), held
                start, held, total = i + 1, [], 0
        if held:
            yield batch.slice(start), held
    release()


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))
