"""Terms of triples as canonical strings: `kind/id` for resources, quoted text for literals."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TYPE = "rdf:type"
QUOTE = '"'


def iri(kind: str, key: Column | str) -> Column:
    return F.concat(F.lit(f"{kind}/"), (F.col(key) if isinstance(key, str) else key).cast("string"))


def literal(value: Column | str) -> Column:
    return F.concat(F.lit(QUOTE), (F.col(value) if isinstance(value, str) else value).cast("string"), F.lit(QUOTE))


def money(name: str) -> Column:
    """A double with two decimals as exact text; double to text differs between engines."""
    return literal(F.col(name).cast("decimal(18,2)"))


def day(name: str) -> Column:
    return literal(F.date_format(name, "yyyy-MM-dd"))


def moment(name: str) -> Column:
    return literal(F.date_format(name, "yyyy-MM-dd HH:mm:ss.SSSSSS"))


def is_literal(term: Column) -> Column:
    return term.startswith(QUOTE)


def is_iri(term: Column) -> Column:
    return ~term.startswith(QUOTE)


def term_kind(term: Column) -> Column:
    """`literal`, or what stands before the slash of a resource, or `name` for a bare word."""
    return F.when(is_literal(term), F.lit("literal")).when(term.contains("/"), F.substring_index(term, "/", 1)).otherwise(F.lit("name"))


def lexical(term: Column) -> Column:
    """Text of a literal without its quotes; null for resources."""
    return F.when(is_literal(term), term.substr(F.lit(2), F.length(term) - 2))


def local_id(term: Column) -> Column:
    """What follows the first slash of a resource; null for literals."""
    return F.when(is_iri(term), F.regexp_extract(term, "^[^/]*/(.*)$", 1))


def decode(term: Column, kind: str) -> Column:
    """A literal as a typed value; null where it is none of that type."""
    return lexical(term).try_cast(kind)
