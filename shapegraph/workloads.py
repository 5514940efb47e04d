"""The experiments on the given tables: tree patterns (A), profile shapes (B), translation (C), hub distance (D), worked shapes (E)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans.paths import ID, Inv, Prop, parse_path, path
from .plans.patterns import GraphQuery, PatternNode, leaf, node
from .plans.patterns import Edge as E_
from .plans.shapes import TOP, AtLeast, AtMost, Closed, Compare, Disj, Eq, ForAll, HasValue, Shape, UniqueLang, all_of, any_of, class_target, exactly, less_than, objects_of, some, test
from .sources.graph import TripleGraph, cut

R, FINISHED = HasValue('"R"'), HasValue('"F"')

#: Worked shapes; each conjunction holds its target.
SHAPES: dict[str, Shape] = {
    "E2": all_of(some("hasLine", some("ofPart", class_target("part/PROMO"))), class_target("Order")),
    "E3": all_of(some("inNation"), ForAll(Prop("inNation"), AtMost(1, Prop("name"), TOP) & ForAll(Prop("name"), test("datatype", "string"))), class_target("Customer")),
    "E4": ~Disj(path("^placedBy", "hasLine", "fromSupplier", "inNation"), "inNation") & class_target("Customer"),
    "E4n": Disj(path("^placedBy", "hasLine", "fromSupplier", "inNation"), "inNation") & class_target("Customer"),
    "E5": Eq(ID, "canonical") & class_target("Document"),
    "E6": all_of(some("hasLine"), AtMost(1, Prop("hasLine"), ~some("flag", R)), class_target("Order")),
    "E7": AtMost(0, Prop("hasLine"), TOP) & class_target("Order"),
    "E8": all_of(some("(inOrder/hasLine)*", some("flag", R)), some("inOrder", any_of(HasValue("<order/1>"), HasValue("<order/2>"), HasValue("<order/3>")))),
    "E9": ForAll(Prop("hasLine"), some("lineStatus", FINISHED)) & class_target("Order"),
    "E10": AtMost(5, path("^placedBy"), TOP) & class_target("Customer"),
    "E11": less_than("^hasLine/orderedOn", "shippedOn") & class_target("LineItem"),
    "E11n": ~less_than("^hasLine/orderedOn", "shippedOn") & class_target("LineItem"),
    "E12": ~UniqueLang(path("^linksTo", "title")) & objects_of("linksTo"),
    "E13": Closed(frozenset({"type", "excerpt", "source", "nChars", "canonical", "quotes"})) & class_target("Document"),
    "E13n": ~Closed(frozenset({"type", "excerpt", "source", "nChars", "canonical", "quotes"})) & class_target("Document"),
    "E14": all_of(Eq(path("hasLine", "lineStatus"), "status"), some("hasLine"), class_target("Order")),
    "E15": some("replyTo*", some("role", HasValue('"system"'))),
}

#: Two requests, each a shape with its target.
PAIRED = [all_of(some("placedBy"), any_of(some("hasLine"), some("contains")), class_target("Order")), all_of(some("name"), objects_of("placedBy"))]

#: Tree patterns, three of each template.
PATTERNS: dict[str, PatternNode] = {
    "A1a": node(leaf("status"), leaf("total"), leaf("placedBy"), classes=("Order",)),
    "A1b": node(leaf("excerpt"), leaf("source"), classes=("Document",)),
    "A1c": node(leaf("name"), leaf("brand"), leaf("price"), classes=("Part",)),
    "A2a": node(E_("placedBy", node(leaf("name"))), classes=("Order",)),
    "A2b": node(E_("inNation", node(leaf("name"))), classes=("Supplier",)),
    "A2c": node(E_("replyTo", node(leaf("role"))), classes=("Turn",)),
    "A3a": node(E_("placedBy", node(E_("inNation", node(leaf("inRegion"))))), classes=("Order",)),
    "A3b": node(E_("fromSupplier", node(E_("inNation", node(leaf("inRegion"))))), classes=("LineItem",)),
    "A3c": node(E_("next", node(E_("next", node(leaf("at"))))), classes=("Event",)),
    "A4a": node(leaf("name"), E_("^ofPart", node(leaf("quantity"))), classes=("Part",)),
    "A4b": node(leaf("name"), E_("^placedBy", node(leaf("status"))), classes=("Customer",)),
    "A4c": node(leaf("title"), E_("linksTo", node(leaf("^linksTo"))), classes=("Page",)),
    "A5a": node(leaf("inNation", value="<nation/7>"), classes=("Customer",)),
    "A5b": node(leaf("brand", value="<brand/17>"), classes=("Part",)),
    "A5c": node(leaf("source", value="<source/src3>"), classes=("Document",)),
    "A6a": node(leaf("total", test=("above", 400000)), classes=("Order",)),
    "A6b": node(leaf("size", test=("max", 10)), classes=("Part",)),
    "A6c": node(leaf("value", test=("above", 100)), classes=("Event",)),
    "A7a": node(leaf("excerpt", test=("lang", "en")), leaf("quality", "optional"), classes=("Document",)),
    "A7b": node(leaf("title", test=("lang", "fr")), leaf("linksTo", "optional"), classes=("Page",)),
    "A7c": node(leaf("excerpt", test=("lang", "de")), leaf("toxic", "optional"), classes=("Document",)),
    "A8a": node(leaf("url", test=("pattern", "^https")), classes=("Page",)),
    "A8b": node(leaf("name", test=("pattern", "^red")), classes=("Part",)),
    "A8c": node(leaf("name", test=("pattern", "0$")), classes=("Customer",)),
    "A9a": node(E_("quotes", node(leaf("excerpt")), "optional"), classes=("Document",)),
    "A9b": node(E_("hasLine", node(leaf("flag", value='"R"')), "optional"), classes=("Order",)),
    "A9c": node(E_("replyTo", node(leaf("role")), "optional"), classes=("Turn",)),
    "A10a": node(E_("hasLine", node(leaf("flag", value='"A"'))), E_("hasLine", node(leaf("flag", value='"R"')), "absent"), classes=("Order",)),
    "A10b": node(leaf("supplies", value="<part/1>"), leaf("supplies", "absent", value="<part/2>"), classes=("Supplier",)),
    "A10c": node(leaf("toxic", "absent", value='"1"^^integer'), classes=("Document",)),
    "A11a": node(E_("ofPart", node(leaf("name"), leaf("brand"))), E_("fromSupplier", node(leaf("name"), leaf("inNation"))), classes=("LineItem",)),
    "A11b": node(E_("placedBy", node(leaf("name"), classes=("Customer",))), E_("contains", node(leaf("price"))), classes=("Order",)),
    "A11c": node(leaf("byUser"), E_("next", node(leaf("at"), leaf("value"))), classes=("Event",)),
    "A12a": node(leaf("name"), classes=("Customer",)),
    "A12b": node(leaf("at"), classes=("Interaction",)),
    "A12c": node(leaf("size"), classes=("Part",)),
    "A13a": node(leaf("price"), classes=("part/PROMO", "part/ECONOMY")),
    "A13b": node(leaf("at"), classes=("event/error", "event/signup")),
    "A13c": node(leaf("balance"), classes=("seg/BUILDING", "seg/HOUSEHOLD")),
}

#: Per class: its properties with the datatype of literals, or None for references.
CLASSES: dict[str, dict[str, str | None]] = {
    "Region": {"name": "string"}, "Nation": {"name": "string", "inRegion": None}, "Customer": {"name": "string", "balance": "decimal", "inNation": None},
    "Supplier": {"name": "string", "balance": "decimal", "inNation": None}, "Part": {"name": "string", "size": "integer", "price": "decimal", "brand": None},
    "Order": {"status": "string", "total": "decimal", "orderedOn": "date", "placedBy": None}, "LineItem": {"quantity": "decimal", "flag": "string", "shippedOn": "date", "ofPart": None, "fromSupplier": None},
    "Event": {"at": "dateTime", "value": "decimal", "k": "integer", "byUser": None}, "Document": {"nChars": "integer", "source": None}, "Page": {"url": "string", "host": None}, "Turn": {"role": "string", "chars": "integer", "inConv": None},
}


#: Per class: further tests on the values of its literals (ranges, patterns, lengths).
VALUES: dict[str, list[tuple[str, Shape]]] = {
    "Region": [("name", test("pattern", "^[A-Z ]+$"))], "Nation": [("name", test("maxLength", 25))], "Customer": [("balance", test("min", -1000)), ("name", test("pattern", "^Customer"))],
    "Supplier": [("balance", test("above", 0))], "Part": [("size", test("min", 1) & test("max", 40)), ("price", test("above", 900))], "Order": [("status", test("in", ('"F"', '"O"'))), ("orderedOn", test("min", "1995-01-01"))],
    "LineItem": [("quantity", test("max", 45)), ("shippedOn", test("below", "2001-01-01"))], "Event": [("value", test("below", 400)), ("k", test("min", 0))], "Document": [("excerpt", test("lang", "en")), ("nChars", test("min", 1))],
    "Page": [("url", test("pattern", "^https?://")), ("title", test("minLength", 1))], "Turn": [("role", test("in", ('"user"', '"assistant"')))],
}

#: Per class: what its references lead to, and references that must lead to it.
REFERENCES: dict[str, Shape] = {
    "Region": some("^inRegion", class_target("Nation")),
    "Nation": all_of(ForAll(Prop("inRegion"), class_target("Region")), some("^inNation")),
    "Customer": all_of(ForAll(Prop("inNation"), class_target("Nation")), some("^placedBy")),
    "Supplier": all_of(ForAll(Prop("inNation"), class_target("Nation")), some("supplies", class_target("Part"))),
    "Part": all_of(ForAll(Inv(Prop("supplies")), class_target("Supplier")), some("brand", test("iri"))),
    "Order": all_of(ForAll(Prop("placedBy"), any_of(class_target("seg/BUILDING"), class_target("seg/MACHINERY"), class_target("seg/HOUSEHOLD"))), some("hasLine")),
    "LineItem": all_of(ForAll(Prop("ofPart"), class_target("Part")), ForAll(Prop("fromSupplier"), class_target("Supplier")), some("^hasLine")),
    "Event": all_of(ForAll(Prop("next"), any_of(class_target("SystemEvent"), class_target("Interaction"))), some("byUser", test("iri"))),
    "Document": all_of(ForAll(Prop("canonical"), class_target("Document")), some("^canonical")),
    "Page": all_of(some("linksTo", test("iri")), some("host")),
    "Turn": all_of(ForAll(Prop("replyTo"), class_target("Turn")), some("^replyTo")),
}

#: Per class: an atom over two paths.
PAIRS: dict[str, Shape] = {
    "Region": all_of(Disj(path("^inRegion", "name"), "name"), UniqueLang(Prop("name"))),
    "Nation": Disj(path("inRegion", "name"), "name"),
    "Customer": ~Disj(path("^placedBy", "hasLine", "fromSupplier", "inNation"), "inNation"),
    "Supplier": Eq(path("^fromSupplier", "ofPart"), "supplies"),
    "Part": all_of(Compare(Prop("size"), "<", "price"), Disj(ID, "brand")),
    "Order": ~Compare(path("hasLine", "shippedOn"), ">=", "orderedOn"),
    "LineItem": Compare(path("^hasLine", "orderedOn"), "<=", "shippedOn"),
    "Event": Compare(path("next", "at"), ">=", "at"),
    "Document": ~Eq(ID, "canonical"),
    "Page": ~UniqueLang(path("linksTo", "^linksTo", "title")),
    "Turn": all_of(Disj(path("replyTo", "role"), "role"), ~Eq(path("replyTo", "chars"), "chars")),
}


def profile_shapes() -> dict[str, tuple[str, Shape]]:
    """58 shapes with their target classes: three analogues and five profiles of each class."""
    out: dict[str, tuple[str, Shape]] = {
        "B-addr": ("Customer", all_of(exactly(1, Prop("name")), ForAll(Prop("name"), test("datatype", "string")), exactly(1, Prop("inNation")), ForAll(Prop("inNation"), test("iri")), some("balance"), ForAll(Prop("balance"), test("datatype", "decimal")), exactly(1, Prop("type")))),
        "B-hours": ("SystemEvent", all_of(ForAll(Prop("at"), test("datatype", "dateTime")), ForAll(Prop("value"), test("datatype", "decimal")), ForAll(Prop("byUser"), test("iri")), ForAll(Prop("k"), test("datatype", "integer")), AtMost(1, Prop("next"), TOP), ForAll(Prop("next"), test("iri")))),
        "B-offer": ("Part", all_of(exactly(1, Prop("name")), exactly(1, Prop("price")), exactly(1, Prop("size")), AtMost(1, Prop("brand"), TOP), ForAll(Prop("price"), test("datatype", "decimal")), some("^supplies"), ForAll(Inv(Prop("supplies")), class_target("Supplier")))),
    }
    for name, props in CLASSES.items():
        first = next(iter(props))
        out[f"B-{name}-card"] = (name, all_of(*(exactly(1, Prop(p)) for p in props)))
        out[f"B-{name}-value"] = (name, all_of(*(ForAll(Prop(p), test("datatype", d)) for p, d in props.items() if d), *(ForAll(Prop(p), x) for p, x in VALUES[name])))
        out[f"B-{name}-ref"] = (name, REFERENCES[name])
        out[f"B-{name}-pair"] = (name, PAIRS[name])
        out[f"B-{name}-neg"] = (name, all_of(~Closed(frozenset({first, "quotes"})), any_of(~some(first, test("blank")), AtMost(0, Prop(first), TOP)), ~Disj(Prop("type"), "type")))
    return out


HUB_PATH = parse_path("^contains/contains/^contains/contains/^contains/contains")


def hub(sf_dir: str, spark: SparkSession) -> str:
    """The part in most orders, ties to the smallest key. Orders are told apart only for parts of as many lines as the orders of
    the part with most lines: no other part can be in more."""
    line = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    lines = line.groupBy("l_partkey").agg(F.count("l_orderkey").alias("lines"))
    most = lines.orderBy(F.desc("lines"), "l_partkey").first()["l_partkey"]
    least = line.where(F.col("l_partkey").eqNullSafe(most)).agg(F.count_distinct("l_orderkey").alias("n")).first()["n"]
    able = cut(lines.where(F.col("lines") >= least).select("l_partkey"), "able")
    counted = line.join(able, line["l_partkey"].eqNullSafe(able["l_partkey"]), "left_semi").groupBy("l_partkey").agg(F.count_distinct("l_orderkey").alias("n"))
    top = counted.orderBy(F.desc("n"), "l_partkey").first()
    return f"<part/{top['l_partkey']}>"


#: Orders that a chain of shared parts joins to one with the hub: a loop over a cyclic, skewed relation.
CHAIN = parse_path("(contains/^contains)*")


def chain_request(node_: str) -> Shape:
    return AtLeast(1, CHAIN, some("contains", HasValue(node_)))


#: Queries beside the 39 patterns, as atoms over variables (``?x``), with what else they compute.
BEYOND: dict[str, GraphQuery] = {
    "N1": GraphQuery((("?order", "priority", '"1-URGENT"'), ("?order", "?any", "?value"))),
    "N2": GraphQuery((("?supplier", "?any", "?customer"),)),
    "N3": GraphQuery((("?customer", "?any", "?value"), ("?supplier", "?any", "?value"))),
    "N4": GraphQuery((("?line", "extPrice", "?e"), ("?line", "discount", "?d")), computed=(("?e", "?d"),)),
    "N5": GraphQuery((("?order", "total", "?t"), ("?order", "hasLine", "?line"), ("?line", "extPrice", "?e")), computed=(("?t", "?e"),)),
    "N6": GraphQuery((("?f", "placedBy", "?customer"), ("?n", "placedBy", "?customer")), counted=("?f", "?n")),
    "N7": GraphQuery(tuple((f"?{a}{b}", "contains", f"?{x}") for a, b in ("ab", "ac", "ad", "bc", "bd", "cd") for x in (a, b))),
}


def contains_slice(g: TripleGraph, since: str) -> TripleGraph:
    """Only ``contains`` triples of orders from a date on. The orders are written, so that their size is known when they are
    joined, and rows that repeat are dropped after that."""
    recent = cut(g.prop("orderedOn").where(F.col("o") >= f'"{since}"').select("s"), "recent")
    return TripleGraph(g.spark, {"contains": g.raw("contains").join(recent, "s", "left_semi").select("s", "o").distinct()})


SLICES = ["2001-07-01", "2001-05-01", "2001-03-01", "2001-01-01", "2000-07-01", "2000-01-01", "1995-01-01"]


def segments(g: TripleGraph, upto: int, of: int = 5) -> TripleGraph:
    """The first ``upto`` fifths: dimension subjects are all in the first, others spread by a hash of the subject."""
    fixed = F.col("s").rlike("^<(region|nation|part|supp|class)/")
    keep = fixed | (F.pmod(F.xxhash64("s"), F.lit(of)) < upto)
    return g.where(keep)


def hub_request(node_: str) -> Shape:
    return some(HUB_PATH, HasValue(node_))


__all__ = ["BEYOND", "CHAIN", "PAIRED", "PATTERNS", "SHAPES", "SLICES", "DataFrame", "chain_request", "contains_slice", "hub", "hub_request", "profile_shapes", "segments"]
