"""A graph as a distinct set of (s, p, o), kept by property so that a query scans only the properties it names."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator, Mapping, Sequence
from dataclasses import dataclass
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TRIPLES = "s string, p string, o string"
#: Most rows of a property of the vocabulary, such as subclass links, that the driver may hold.
MOST_VOCABULARY = 20_000
_own: list[str] = []


def fresh_path(spark: SparkSession, tag: str) -> str:
    """A new folder below ``spark.checkpoint.dir``; below a temporary one only if that is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not _own:
            _own.append(tempfile.mkdtemp(prefix="shapegraph-"))
            atexit.register(shutil.rmtree, _own[0], True)
        named = f"file://{_own[0]}"
    return f"{named}/{tag}-{uuid.uuid4().hex}"


def cut(df: DataFrame, tag: str = "cut") -> DataFrame:
    """Truncate lineage by a table in the shared folder."""
    path = fresh_path(df.sparkSession, tag)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def local(spark: SparkSession, rows: Iterable[Sequence[object]], **columns: pa.DataType) -> DataFrame:
    """Rows that the driver holds as a local relation: the optimizer knows their size and prunes what joins with none."""
    rows = list(rows)
    return spark.createDataFrame(pa.table({c: pa.array([r[i] for r in rows], t) for i, (c, t) in enumerate(columns.items())}))


class LazyParts(Mapping[str, DataFrame]):
    """Property -> DataFrame, planned when it is first read: a request pays for the tables of the properties it names."""

    def __init__(self, makers: Mapping[str, Callable[[], DataFrame]]):
        self._makers, self._made = dict(makers), {}

    def __getitem__(self, p: str) -> DataFrame:
        if p not in self._made:
            self._made[p] = self._makers[p]()
        return self._made[p]

    def __contains__(self, p: object) -> bool:
        return p in self._makers

    def __iter__(self) -> Iterator[str]:
        return iter(self._makers)

    def __len__(self) -> int:
        return len(self._makers)

    def mapped(self, change: Callable[[DataFrame], DataFrame], names: Iterable[str] | None = None) -> LazyParts:
        return LazyParts({p: (lambda p=p: change(self[p])) for p in (self if names is None else names) if p in self})


@dataclass(frozen=True)
class Kinds:
    """How subjects begin (``<order/``): those of each property that is named, and those of a class's own instances."""

    subjects: Mapping[str, frozenset[str]]
    instances: Callable[[str], frozenset[str]]


@dataclass(frozen=True)
class Rows:
    """A table whose rows each hold triples of one node, as ``view`` with the column ``node``, whether it is ``known`` (not null)
    and one column per property: ``out`` are those that only these nodes have, ``into`` those that only lead to them, ``told``
    those whose other end the node's term tells. ``klass``: the one type of all these nodes, a class without superclasses that
    no others have. ``ends``: how objects of a property begin. ``single``: steps of any table to at most one node, as texts of paths."""

    view: str
    make: Callable[[], DataFrame]
    out: frozenset[str]
    into: frozenset[str]
    told: frozenset[str]
    ends: Mapping[str, str]
    single: frozenset[str]
    klass: str


def of_kinds(c: Column, kinds: frozenset[str]) -> Column:
    return reduce(lambda a, b: a | b, (c.startswith(k) for k in sorted(kinds)), F.lit(False))


class TripleGraph:
    """parts: property -> DataFrame[s, o] with distinct rows; vocabulary: properties whose size belongs to the schema; bags:
    the same rows of a property, some more than once, where reading them so saves a shuffle; kinds: what the mapping knows of
    its subjects, so that tables without a request's kind of node are left out; pieces: a property of several tables by the
    kind of its subjects, as its part and as its bag; rows: a table that holds several properties of a node in one row."""

    def __init__(self, spark: SparkSession, parts: Mapping[str, DataFrame], vocabulary: frozenset[str] = frozenset(), bags: Mapping[str, DataFrame] | None = None, kinds: Kinds | None = None, pieces: Mapping[str, tuple[LazyParts, LazyParts]] | None = None, rows: Rows | None = None):
        self.spark, self.vocabulary, self.kinds, self.pieces, self.rows = spark, vocabulary, kinds, dict(pieces or {}), rows
        self.parts, self.bags = (x if isinstance(x, LazyParts) else LazyParts({p: (lambda df=df: df) for p, df in x.items()}) for x in (parts, bags or {}))
        self._rows: dict[str, list[tuple[str, str]] | None] = {}

    def vocabulary_rows(self, p: str) -> list[tuple[str, str]] | None:
        """All rows of a vocabulary property, or None for other properties and for those of more than ``MOST_VOCABULARY``."""
        if p not in self.vocabulary:
            return None
        if p not in self._rows:
            rows = [(r["s"], r["o"]) for r in self.prop(p).limit(MOST_VOCABULARY + 1).collect()]
            self._rows[p] = rows if len(rows) <= MOST_VOCABULARY else None
        return self._rows[p]

    @classmethod
    def of(cls, df: DataFrame, properties: Iterable[str] | None = None, vocabulary: frozenset[str] = frozenset()) -> TripleGraph:
        """From a table of triples; without a list, its properties are looked up (they belong to the schema, not the data)."""
        rows = df.select("s", "p", "o").distinct()
        names = sorted(r["p"] for r in rows.select("p").distinct().collect()) if properties is None else list(properties)
        bag = df.select("s", "p", "o")
        return cls(df.sparkSession, {p: rows.where(F.col("p") == p).select("s", "o") for p in names}, vocabulary, {p: bag.where(F.col("p") == p).select("s", "o") for p in names})

    @classmethod
    def from_rows(cls, spark: SparkSession, rows: Iterable[tuple[str, str, str]], vocabulary: frozenset[str] = frozenset()) -> TripleGraph:
        """Rows that the driver holds: one local relation per property."""
        by: dict[str, set[tuple[str, str]]] = {}
        for s, p, o in rows:
            by.setdefault(p, set()).add((s, o))
        return cls(spark, {p: local(spark, sorted(x), s=pa.string(), o=pa.string()) for p, x in sorted(by.items())}, vocabulary)

    def prop(self, p: str) -> DataFrame:
        return self.parts[p] if p in self.parts else local(self.spark, [], s=pa.string(), o=pa.string())

    def raw(self, p: str) -> DataFrame:
        """Rows of a property that may repeat: for all that ends in a set or asks whether there is a row."""
        return self.bags[p] if p in self.bags else self.prop(p)

    def triples(self, properties: Iterable[str] | None = None, exact: bool = True) -> DataFrame:
        """Rows may repeat unless ``exact``, as in ``raw``."""
        wanted = None if properties is None else set(properties)
        named = [(self.parts[p] if exact else self.raw(p)).select("s", F.lit(p).alias("p"), "o") for p in self.parts if wanted is None or p in wanted]
        return reduce(DataFrame.unionAll, named) if named else local(self.spark, [], s=pa.string(), p=pa.string(), o=pa.string())

    def nodes(self) -> DataFrame:
        rows = [self.raw(p) for p in self.parts]
        ends = [x.select(F.col(c).alias("v")) for x in rows for c in ("s", "o")]
        return reduce(DataFrame.unionAll, ends).distinct() if ends else local(self.spark, [], v=pa.string())

    def cached(self) -> TripleGraph:
        return TripleGraph(self.spark, {p: cut(x, "graph") for p, x in self.parts.items()}, self.vocabulary, kinds=self.kinds)

    def union(self, other: TripleGraph) -> TripleGraph:
        names = {**self.parts, **other.parts}
        return TripleGraph(self.spark, {p: self.prop(p).union(other.prop(p)).distinct() for p in names})

    def intersect(self, other: TripleGraph) -> TripleGraph:
        return TripleGraph(self.spark, {p: x.join(other.prop(p), ["s", "o"], "left_semi") for p, x in self.parts.items()})

    def minus(self, other: TripleGraph) -> TripleGraph:
        return TripleGraph(self.spark, {p: x.join(other.prop(p), ["s", "o"], "left_anti") for p, x in self.parts.items()})

    def induced(self, nodes: DataFrame) -> TripleGraph:
        """Triples between the given nodes (column v)."""
        s, o = nodes.select(F.col("v").alias("s")), nodes.select(F.col("v").alias("o"))
        return TripleGraph(self.spark, {p: x.join(s, "s", "left_semi").join(o, "o", "left_semi").select("s", "o") for p, x in self.parts.items()})

    def restrict(self, properties: Iterable[str]) -> TripleGraph:
        named = list(properties)
        return TripleGraph(self.spark, self.parts.mapped(lambda x: x, named), self.vocabulary, self.bags.mapped(lambda x: x, named), self.kinds, {p: x for p, x in self.pieces.items() if p in named})

    def where(self, keep: Column) -> TripleGraph:
        """Triples whose columns s and o pass the condition."""
        pieces = {p: tuple(x.mapped(lambda y: y.where(keep)) for x in both) for p, both in self.pieces.items()}
        return TripleGraph(self.spark, self.parts.mapped(lambda x: x.where(keep)), self.vocabulary, self.bags.mapped(lambda x: x.where(keep)), self.kinds, pieces)

    def about(self, kinds: frozenset[str]) -> TripleGraph:
        """Triples whose subjects are of the kinds; properties of other subjects, and their other tables, are neither planned
        nor read."""
        known = self.kinds.subjects if self.kinds else {}
        named = [p for p in self.parts if (frozenset(self.pieces[p][0]) if p in self.pieces else known.get(p, kinds)) & kinds]

        def made(p: str, bag: bool) -> DataFrame:
            if p in self.pieces:
                both = self.pieces[p][bag]
                return reduce(DataFrame.unionAll, [both[k] for k in both if k in kinds])
            x = self.raw(p) if bag else self.parts[p]
            return x if p in known and known[p] <= kinds else x.where(of_kinds(F.col("s"), kinds))

        parts, bags = (LazyParts({p: (lambda p=p, bag=bag: made(p, bag)) for p in named}) for bag in (False, True))
        pieces = {p: tuple(x.mapped(lambda y: y, [k for k in x if k in kinds]) for x in both) for p, both in self.pieces.items() if p in named}
        return TripleGraph(self.spark, parts, self.vocabulary, bags, self.kinds, pieces)

    def stats(self) -> DataFrame:
        return self.triples().groupBy("p").agg(F.count("*").alias("triples"), F.approx_count_distinct("s").alias("subjects"), F.approx_count_distinct("o").alias("objects"))

    def degrees(self) -> DataFrame:
        t = self.triples()
        ends = t.select(F.col("s").alias("v"), F.lit(1).alias("out_degree"), F.lit(0).alias("in_degree")).union(t.select("o", F.lit(0), F.lit(1)))
        return ends.groupBy("v").agg(F.sum("out_degree").alias("out_degree"), F.sum("in_degree").alias("in_degree"))


def check_triples(df: DataFrame) -> DataFrame:
    """Rows that are no triples: literal subjects, properties that are empty or null, null positions."""
    return df.where(F.col("s").isNull() | F.col("p").isNull() | F.col("o").isNull() | F.col("s").startswith('"') | (F.col("p") == ""))


def save_graph(g: TripleGraph, table: str, buckets: int = 8, by: str = "s") -> None:
    """A catalog table partitioned by property and bucketed by subject or object, for joins without a shuffle."""
    g.triples().write.mode("overwrite").partitionBy("p").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def load_graph(spark: SparkSession, table: str, properties: Iterable[str]) -> TripleGraph:
    rows = spark.table(table)
    return TripleGraph(spark, {p: rows.where(F.col("p") == p).select("s", "o") for p in properties})


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """Line-based triple text: subject, property in angle brackets, object, full stop."""
    line = F.col("value")
    parts = r'^(\S+)\s+<([^>]*)>\s+(.*?)\s*\.\s*$'
    return spark.read.text(path).where(line.rlike(parts)).select(*(F.regexp_extract(line, parts, i).alias(c) for i, c in ((1, "s"), (2, "p"), (3, "o"))))


def write_lines(df: DataFrame, path: str) -> None:
    df.select(F.concat_ws(" ", "s", F.concat(F.lit("<"), "p", F.lit(">")), "o", F.lit("."))).write.mode("overwrite").text(path)
