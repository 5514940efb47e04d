"""The given tables as a graph: one function of columns per property."""

from __future__ import annotations

from functools import cache, reduce

import pyarrow
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.terms import day, decimal, integer, iri, literal, moment, tagged, text
from .graph import Kinds, LazyParts, Rows, TripleGraph, local

LINE = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")

#: Direct superclasses (fixed values); segment, part-type and event-type classes are added from the tables' own rules.
SUBCLASSES = [("Customer", "Party"), ("Party", "Thing"), ("Part", "Thing"), ("Event", "Thing"), ("SystemEvent", "Event"), ("Interaction", "Event")]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
#: How the subjects of each property but ``type`` begin, and how instances of classes do; other classes only have subclasses.
SUBJECTS = {
    "class": "subClassOf", "cust": "name inNation balance", "supp": "name inNation balance supplies", "part": "name brand size price", "nation": "name inRegion", "region": "name",
    "order": "placedBy status total orderedOn priority hasLine contains", "line": "inOrder ofPart fromSupplier quantity extPrice discount tax flag lineStatus shippedOn", "event": "byUser at value k next",
    "doc": "excerpt source nChars canonical quotes quality toxic", "bench": "excerpt", "page": "url host title linksTo", "turn": "inConv role chars replyTo", "vec": "label norm",
}
INSTANCES = {"seg": "cust", "part": "part", "event": "event", "Supplier": "supp", "Order": "order", "LineItem": "line", "Document": "doc", "Page": "page", "Turn": "turn", "BenchItem": "bench", "Region": "region", "Nation": "nation", "Vector": "vec"}
#: Steps to at most one node besides those from a line, and what a line's own term tells.
SINGLE = "type subClassOf* name inNation balance inRegion brand size price placedBy status total orderedOn priority byUser at value k next ^next source nChars canonical quality toxic url host title inConv role chars replyTo label norm ^hasLine"
TOLD = "hasLine inOrder ofPart fromSupplier shippedOn"
EVENTS = {"error": "SystemEvent", "click": "Interaction", "view": "Interaction", "purchase": "Event", "signup": "Event"}


def kinds() -> Kinds:
    subjects = {p: frozenset(f"<{k}/" for k, names in SUBJECTS.items() if p in names.split()) for names in SUBJECTS.values() for p in names.split()}

    def instances(c: str) -> frozenset[str]:
        name, _, rest = c.removeprefix("<class/").removesuffix(">").partition("/")
        known = name in INSTANCES and c.startswith(f"<class/{name}/" if name in ("seg", "part", "event") else f"<class/{name}>")
        return frozenset({f"<{INSTANCES[name]}/"}) if known else frozenset()

    return Kinds(subjects, instances)


def line_iri() -> Column:
    return iri("line", *LINE, F.date_format("l_shipdate", "yyyyMMdd"))


def containing(docs: DataFrame, items: DataFrame) -> DataFrame:
    """item_id, doc_id where a document's text contains an item's: an equi-join on three words inside the item, then the
    whole text. The words between an item's first and last are whole words wherever it occurs; only items with fewer than
    five are compared with all documents."""
    key = lambda words, at: F.xxhash64(*(F.get(words, at + k) for k in range(3)))
    items = items.select("item_id", F.col("text").alias("item"), F.split("text", r"\s+").alias("words"))
    docs = docs.select("doc_id", "text", F.split("text", r"\s+").alias("words"))
    long, short = items.where(F.size("words") >= 5), items.where(F.size("words") < 5)
    keyed = docs.where(F.size("words") >= 3).select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(0), F.size("words") - 3), lambda i: key(F.col("words"), i)))).alias("key"))
    near = keyed.join(long.select("item_id", "item", key(F.col("words"), F.lit(1)).alias("key")), "key").select("item_id", "item", "doc_id").distinct()
    found = near.join(docs.select("doc_id", "text"), "doc_id").where(F.contains("text", "item")).select("item_id", "doc_id")
    return found.unionAll(docs.join(short, F.contains(docs["text"], short["item"])).select("item_id", "doc_id"))


def build_graph(spark: SparkSession, sf_dir: str) -> TripleGraph:
    """All properties, each a lazy projection of its table; only those that a request names are ever planned or scanned."""

    @cache
    def t(name: str) -> DataFrame:
        return spark.read.parquet(f"{sf_dir}/{name}.parquet")

    def rows(name: str, s: Column, o: Column) -> DataFrame:
        return t(name).select(s.alias("s"), o.alias("o")).where("s is not null and o is not null")

    def union(*frames: DataFrame) -> DataFrame:
        return reduce(DataFrame.unionAll, frames)

    def klass(name: str) -> Column:
        return F.lit(f"<class/{name}>")

    c, su, pa, o, ln = iri("cust", "c_custkey"), iri("supp", "s_suppkey"), iri("part", "p_partkey"), iri("order", "o_orderkey"), line_iri()
    ev, d, pg, tu, bench = iri("event", "event_id"), iri("doc", "doc_id"), iri("page", "page_id"), iri("turn", "conv_id", "turn"), iri("bench", "item_id")
    nation, region, vec = iri("nation", "n_nationkey"), iri("region", "r_regionkey"), iri("vec", "vec_id")
    part_class = iri("class/part", F.regexp_extract("p_type", r"^(\S+)", 1))
    title, page_lang = F.regexp_extract("html", r"(?s)<title>(.*?)</title>", 1), F.regexp_extract("html", r'<html lang="([a-z]+)"', 1)

    # Properties of several tables, by the kind of their subjects.
    types = {
        "cust": lambda: rows("customer", c, iri("class/seg", "c_mktsegment")), "supp": lambda: rows("supplier", su, klass("Supplier")), "part": lambda: rows("part", pa, part_class), "order": lambda: rows("orders", o, klass("Order")),
        "line": lambda: rows("lineitem", ln, klass("LineItem")), "event": lambda: rows("events", ev, iri("class/event", "event_type")), "doc": lambda: rows("documents", d, klass("Document")), "page": lambda: rows("pages", pg, klass("Page")),
        "turn": lambda: rows("conversations", tu, klass("Turn")), "bench": lambda: rows("benchmark", bench, klass("BenchItem")), "region": lambda: rows("region", region, klass("Region")), "nation": lambda: rows("nation", nation, klass("Nation")), "vec": lambda: rows("embeddings", vec, klass("Vector")),
    }
    mixed = {
        "type": types,
        "name": {
            "cust": lambda: rows("customer", c, text(F.col("c_name"))), "supp": lambda: rows("supplier", su, text(F.col("s_name"))), "part": lambda: rows("part", pa, text(F.col("p_name"))),
            "nation": lambda: rows("nation", nation, text(F.col("n_name"))), "region": lambda: rows("region", region, text(F.col("r_name"))),
        },
        "inNation": {"cust": lambda: rows("customer", c, iri("nation", "c_nationkey")), "supp": lambda: rows("supplier", su, iri("nation", "s_nationkey"))},
        "balance": {"cust": lambda: rows("customer", c, decimal(F.col("c_acctbal"))), "supp": lambda: rows("supplier", su, decimal(F.col("s_acctbal")))},
        "excerpt": {"doc": lambda: rows("documents", d, tagged(F.substring("text", 1, 64), F.col("lang"))), "bench": lambda: rows("benchmark", bench, text(F.substring("text", 1, 64)))},
    }

    def pieces(p: str, exact: bool) -> LazyParts:
        """Lines may repeat in their table."""
        found = LazyParts({f"<{k}/": make for k, make in mixed[p].items()})
        return found if not exact or p != "type" else LazyParts({k: (lambda k=k: found[k].distinct() if k == "<line/" else found[k]) for k in found})

    by_kind = {p: (pieces(p, True), pieces(p, False)) for p in mixed}

    def subclasses() -> DataFrame:
        known = [(f"<class/{a}>", f"<class/{b}>") for a, b in SUBCLASSES] + [(f"<class/seg/{x}>", "<class/Customer>") for x in SEGMENTS] + [(f"<class/event/{e}>", f"<class/{k}>") for e, k in EVENTS.items()]
        return local(spark, known, s=pyarrow.string(), o=pyarrow.string()).union(t("part").select(part_class.alias("s"), klass("Part").alias("o")).distinct())

    def next_events() -> DataFrame:
        after = F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id"))
        return t("events").withColumn("next_id", after).select(ev.alias("s"), iri("event", "next_id").alias("o")).where("o is not null")

    def replies() -> DataFrame:
        before = F.lag("turn").over(W.partitionBy("conv_id").orderBy("turn"))
        return t("conversations").withColumn("previous", before).select(tu.alias("s"), iri("turn", "conv_id", "previous").alias("o")).where("o is not null")

    def first_copies() -> DataFrame:
        """By SHA-256 of the text, so that groups are told apart by a digest of fixed width."""
        same = W.partitionBy(F.sha2(F.col("text"), 256))
        return t("documents").where("text is not null").withColumn("first_id", F.min("doc_id").over(same)).select(d.alias("s"), iri("doc", "first_id").alias("o")).where("s is not null and o is not null")

    def links() -> DataFrame:
        return t("pages").select(pg.alias("s"), F.explode(F.regexp_extract_all("html", F.lit(r'href="(/[^"]*)"'), 1)).alias("path")).select("s", F.concat(F.lit("<path"), "path", F.lit(">")).alias("o")).where("s is not null")

    def quotes() -> DataFrame:
        return containing(t("documents"), t("benchmark")).select(d.alias("s"), bench.alias("o"))

    # Lines may repeat in their table, so what is read from them is made distinct, save where a bag of rows does.
    order, part, supp = iri("order", "l_orderkey"), iri("part", "l_partkey"), iri("supp", "l_suppkey")
    of_line = {
        "inOrder": order, "ofPart": part, "fromSupplier": supp, "quantity": decimal(F.col("l_quantity")), "extPrice": decimal(F.col("l_extendedprice")), "discount": decimal(F.col("l_discount")),
        "tax": decimal(F.col("l_tax")), "flag": literal(F.col("l_returnflag")), "lineStatus": literal(F.col("l_linestatus")), "shippedOn": day(F.col("l_shipdate")),
    }
    line_parts = {
        "supplies": lambda: rows("lineitem", supp, part),
        "hasLine": lambda: rows("lineitem", order, ln),
        "contains": lambda: rows("lineitem", order, part),
        **{p: (lambda x=x: rows("lineitem", ln, x)) for p, x in of_line.items()},
    }
    line_rows = Rows(
        "rows_line", lambda: t("lineitem").select(ln.alias("node"), reduce(Column.__and__, (F.col(c).isNotNull() for c in (*LINE, "l_shipdate"))).alias("known"), order.alias("hasLine"), *(x.alias(p) for p, x in of_line.items())), frozenset(of_line), frozenset({"hasLine"}), frozenset(TOLD.split()),
        {"inOrder": "<order/", "ofPart": "<part/", "fromSupplier": "<supp/"}, frozenset([*of_line, *SINGLE.split()]), "<class/LineItem>",
    )
    parts = {
        "subClassOf": subclasses,
        "inRegion": lambda: rows("nation", nation, iri("region", "n_regionkey")),
        "brand": lambda: rows("part", pa, iri("brand", F.replace("p_brand", F.lit("Brand#"), F.lit("")))),
        "size": lambda: rows("part", pa, integer(F.col("p_size"))),
        "price": lambda: rows("part", pa, decimal(F.col("p_retailprice"))),
        "placedBy": lambda: rows("orders", o, iri("cust", "o_custkey")),
        "status": lambda: rows("orders", o, literal(F.col("o_orderstatus"))),
        "total": lambda: rows("orders", o, decimal(F.col("o_totalprice"))),
        "orderedOn": lambda: rows("orders", o, day(F.col("o_orderdate"))),
        "priority": lambda: rows("orders", o, literal(F.col("o_orderpriority"))),
        "byUser": lambda: rows("events", ev, iri("user", "user_id")),
        "at": lambda: rows("events", ev, moment(F.col("ts"))),
        "value": lambda: rows("events", ev, decimal(F.col("value"))),
        "k": lambda: rows("events", ev, integer(F.get_json_object("props", "$.k"))),
        "next": next_events,
        "source": lambda: rows("documents", d, iri("source", "source")),
        "nChars": lambda: rows("documents", d, integer(F.col("n_chars"))),
        "canonical": first_copies,
        "quotes": quotes,
        "quality": lambda: rows("labels", d, integer(F.col("quality"))),
        "toxic": lambda: rows("labels", d, integer(F.col("toxic"))),
        "url": lambda: rows("pages", pg, text(F.col("url"))),
        "host": lambda: rows("pages", pg, iri("host", F.regexp_extract("url", "://([^/?#]*)", 1))),
        "title": lambda: rows("pages", pg, tagged(title, page_lang)),
        "linksTo": lambda: links().distinct(),
        "inConv": lambda: rows("conversations", tu, iri("conv", "conv_id")),
        "role": lambda: rows("conversations", tu, literal(F.col("role"))),
        "chars": lambda: rows("conversations", tu, integer(F.length("text"))),
        "replyTo": replies,
        "label": lambda: rows("embeddings", vec, iri("label", "label")),
        "norm": lambda: rows("embeddings", vec, decimal(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))))),
        **{p: (lambda make=make: make().distinct()) for p, make in line_parts.items()},
        **{p: (lambda x=x: union(*x.values())) for p, (x, _) in by_kind.items()},
    }
    bags = {**line_parts, "type": lambda: union(*by_kind["type"][1].values()), "linksTo": links}
    return TripleGraph(spark, LazyParts(parts), frozenset({"subClassOf"}), LazyParts(bags), kinds(), by_kind, line_rows)
