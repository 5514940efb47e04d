"""Canonical terms as strings, and what they hold, as Column expressions.

``<...>`` is an IRI, ``_:...`` a blank node, ``"..."`` a literal with ``@lang`` or ``^^type``; without either it is a string.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

NUMERIC = ("integer", "decimal", "double")
TEMPORAL = ("date", "dateTime")


def iri(prefix: str, *parts: Column | str) -> Column:
    cols = [F.lit("-") if i % 2 else (F.col(x) if isinstance(x, str) else x).cast("string") for i, x in enumerate(y for p in parts for y in (p, None))][:-1]
    return F.concat(F.lit(f"<{prefix}/"), *cols, F.lit(">"))


def escape(c: Column) -> Column:
    return F.replace(F.replace(F.replace(c, F.lit("\\"), F.lit("\\\\")), F.lit('"'), F.lit('\\"')), F.lit("\n"), F.lit("\\n"))


def literal(c: Column, kind: str | None = None) -> Column:
    return F.concat(F.lit('"'), c.cast("string"), F.lit('"' + (f"^^{kind}" if kind else "")))


def text(c: Column) -> Column:
    return literal(escape(c))


def decimal(c: Column) -> Column:
    return literal(c.cast("decimal(18,2)"), "decimal")


def integer(c: Column) -> Column:
    return literal(c.cast("long"), "integer")


def day(c: Column) -> Column:
    return literal(F.date_format(c, "yyyy-MM-dd"), "date")


def moment(c: Column) -> Column:
    return literal(F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS"), "dateTime")


def tagged(c: Column, lang: Column) -> Column:
    return F.concat(F.lit('"'), escape(c), F.lit('"@'), lang)


def is_iri(t: Column) -> Column:
    return t.startswith("<")


def is_blank(t: Column) -> Column:
    return t.startswith("_:")


def is_literal(t: Column) -> Column:
    return t.startswith('"')


def lexical(t: Column) -> Column:
    """The text between the quotes, or an IRI without its brackets."""
    return F.when(is_literal(t), F.regexp_extract(t, r'(?s)^"(.*)"[^"]*$', 1)).when(is_iri(t), F.substring(t, 2, F.length(t) - 2)).otherwise(t)


def language(t: Column) -> Column:
    """Lower-case tag, empty for untagged literals and other nodes."""
    return F.when(is_literal(t), F.lower(F.regexp_extract(t, r'"@([A-Za-z0-9-]+)$', 1))).otherwise("")


def datatype(t: Column) -> Column:
    found = F.regexp_extract(t, r'"\^\^([A-Za-z]+)$', 1)
    return F.when(~is_literal(t), "").when(found != "", found).when(language(t) != "", "langString").otherwise("string")


def number(t: Column) -> Column:
    """The numeric value, null for other nodes."""
    return F.when(datatype(t).isin(*NUMERIC), lexical(t).try_cast("double"))


def instant(t: Column) -> Column:
    return F.when(datatype(t).isin(*TEMPORAL), lexical(t).try_cast("timestamp_ntz"))


def less(a: Column, b: Column) -> Column:
    """a < b for two numbers, two times or two plain strings; false for all else, NaN included."""
    nan = F.isnan(number(a)) | F.isnan(number(b))
    numbers = F.when(number(a).isNotNull() & number(b).isNotNull(), ~nan & (number(a) < number(b)))
    times = F.when(instant(a).isNotNull() & instant(b).isNotNull(), instant(a) < instant(b))
    strings = F.when((datatype(a) == "string") & (datatype(b) == "string"), lexical(a) < lexical(b))
    return F.coalesce(numbers, times, strings, F.lit(False))


def less_eq(a: Column, b: Column) -> Column:
    comparable = (number(a).isNotNull() & number(b).isNotNull() & ~F.isnan(number(a)) & ~F.isnan(number(b))) | (instant(a).isNotNull() & instant(b).isNotNull()) | ((datatype(a) == "string") & (datatype(b) == "string"))
    equal = F.coalesce(number(a) == number(b), instant(a) == instant(b), lexical(a) == lexical(b))
    return less(a, b) | F.coalesce(comparable & equal, F.lit(False))
