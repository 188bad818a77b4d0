"""The given tables as triples, and the axioms over them."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Mapping

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from probejoin.functions.terms import TYPE, day, iri, literal, moment, money
from probejoin.sources.storage import table

LINE = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def _camel(text: Column, end: str) -> Column:
    return F.concat(F.regexp_replace(F.initcap(F.lower(text)), " ", ""), F.lit(end))


def _line() -> Column:
    return F.concat(F.lit("line/"), F.concat_ws("-", *[F.col(c).cast("string") for c in LINE], F.col("l_extendedprice").cast("decimal(18,2)").cast("string")))




def _spec() -> dict[str, tuple[Callable[[], Column], dict[str, Callable[[], Column]]]]:
    return {
        "region": (lambda: iri("region", "r_regionkey"), {"name": lambda: literal("r_name"), TYPE: lambda: F.lit("Region")}),
        "nation": (lambda: iri("nation", "n_nationkey"), {"name": lambda: literal("n_name"), "inRegion": lambda: iri("region", "n_regionkey"), TYPE: lambda: F.lit("Nation")}),
        "customer": (lambda: iri("customer", "c_custkey"), {"name": lambda: literal("c_name"), "acctbal": lambda: money("c_acctbal"), "segment": lambda: literal("c_mktsegment"), "inNation": lambda: iri("nation", "c_nationkey"), TYPE: lambda: _camel(F.col("c_mktsegment"), "Customer")}),
        "supplier": (lambda: iri("supplier", "s_suppkey"), {"name": lambda: literal("s_name"), "acctbal": lambda: money("s_acctbal"), "inNation": lambda: iri("nation", "s_nationkey"), TYPE: lambda: F.lit("Supplier")}),
        "part": (lambda: iri("part", "p_partkey"), {"name": lambda: literal("p_name"), "brand": lambda: literal("p_brand"), "kind": lambda: literal("p_type"), "size": lambda: literal("p_size"), "retailprice": lambda: money("p_retailprice"), TYPE: lambda: _camel(F.col("p_type"), "Part")}),
        "orders": (lambda: iri("order", "o_orderkey"), {"placedBy": lambda: iri("customer", "o_custkey"), "status": lambda: literal("o_orderstatus"), "totalprice": lambda: money("o_totalprice"), "orderdate": lambda: day("o_orderdate"), "priority": lambda: literal("o_orderpriority"), TYPE: lambda: _camel(F.substring_index("o_orderpriority", "-", -1), "Order")}),
        "lineitem": (_line, {"ofOrder": lambda: iri("order", "l_orderkey"), "ofPart": lambda: iri("part", "l_partkey"), "suppliedBy": lambda: iri("supplier", "l_suppkey"), "lineno": lambda: literal("l_linenumber"), "quantity": lambda: money("l_quantity"), "extendedprice": lambda: money("l_extendedprice"), "discount": lambda: money("l_discount"), "tax": lambda: money("l_tax"), "returnflag": lambda: literal("l_returnflag"), "linestatus": lambda: literal("l_linestatus"), "shipdate": lambda: day("l_shipdate"), TYPE: lambda: F.lit("LineItem")}),
        "events": (lambda: iri("event", "event_id"), {"at": lambda: moment("ts"), "byCustomer": lambda: iri("customer", "user_id"), "eventType": lambda: literal("event_type"), "amount": lambda: money("value"), "propK": lambda: literal(F.get_json_object("props", "$.k")), TYPE: lambda: _camel(F.col("event_type"), "Event")}),
        "documents": (lambda: iri("doc", "doc_id"), {"lang": lambda: literal("lang"), "source": lambda: literal("source"), "nchars": lambda: literal("n_chars"), TYPE: lambda: F.lit("Document")}),
        "labels": (lambda: iri("doc", "doc_id"), {"quality": lambda: literal("quality"), "toxic": lambda: literal("toxic")}),
        "pages": (lambda: iri("page", "page_id"), {"url": lambda: literal("url"), "host": lambda: literal(F.regexp_extract("url", "://([^/?#]*)", 1)), TYPE: lambda: F.lit("WebPage")}),
        "benchmark": (lambda: iri("item", "item_id"), {"text": lambda: literal("text"), TYPE: lambda: F.lit("BenchmarkItem")}),
        "conversations": (lambda: F.concat(F.lit("turn/"), F.concat_ws("-", F.col("conv_id").cast("string"), F.col("turn").cast("string"))), {"inConversation": lambda: iri("conv", "conv_id"), "turnNo": lambda: literal("turn"), "role": lambda: literal("role"), TYPE: lambda: F.lit("Turn")}),
        "embeddings": (lambda: iri("vec", "vec_id"), {"clusterLabel": lambda: literal("label"), TYPE: lambda: F.lit("Vector")}),
    }


TABLES = tuple(_spec())
#: What the experiment workloads read.
CORE = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")


#: How every class that a table's rows are asserted to have ends.
CLASS_END = {"region": "Region", "nation": "Nation", "customer": "Customer", "supplier": "Supplier", "part": "Part", "orders": "Order", "lineitem": "LineItem", "events": "Event"}


def with_classes(tables: Iterable[str], classes: Iterable[str]) -> list[str]:
    """Tables that may have rows of the classes."""
    classes = list(classes)
    return [t for t in tables if t not in CLASS_END or any(c.endswith(CLASS_END[t]) for c in classes)]


def triples(spark: SparkSession, sf_dir: str, tables: Iterable[str] = CORE, predicates: Iterable[str] | None = None) -> DataFrame:
    """Rows (s, p, o), a set. Only the columns of the wanted predicates are read.

    Each table is unpivoted in one pass; the two many-valued predicates come from distinct
    pairs of keys.
    """
    wanted = None if predicates is None else set(predicates)
    parts = []
    for name in tables:
        subject, made = _spec()[name]
        chosen = [(p, o()) for p, o in made.items() if wanted is None or p in wanted]
        if len(chosen) == 1:
            parts.append(table(spark, sf_dir, name).select(subject().alias("s"), F.lit(chosen[0][0]).alias("p"), chosen[0][1].alias("o")))
        elif chosen:
            cells = F.explode(F.array(*[F.struct(F.lit(p).alias("p"), o.alias("o")) for p, o in chosen])).alias("cell")
            parts.append(table(spark, sf_dir, name).select(subject().alias("s"), cells).select("s", "cell.p", "cell.o"))
        if name == "lineitem":
            lines = table(spark, sf_dir, name)
            if wanted is None or "supplies" in wanted:
                parts.append(lines.select("l_suppkey", "l_partkey").distinct().select(iri("supplier", "l_suppkey").alias("s"), F.lit("supplies").alias("p"), iri("part", "l_partkey").alias("o")))
            if wanted is None or "contains" in wanted:
                parts.append(lines.select("l_orderkey", "l_partkey").distinct().select(iri("order", "l_orderkey").alias("s"), F.lit("contains").alias("p"), iri("part", "l_partkey").alias("o")))
    if not parts:
        return spark.createDataFrame([], "s string, p string, o string")
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out.where("s is not null and o is not null")


def alone(predicates: Iterable[str], tables: Iterable[str] = CORE) -> dict[str, list[str]]:
    """Of the predicates, those that a single table has, by table; a table with one of them only is left out."""
    tables = list(tables)
    made = {name: _spec()[name][1] for name in tables}
    out = {name: [p for p in predicates if p in made[name] and not any(p in made[x] for x in tables if x != name)] for name in tables}
    return {name: found for name, found in out.items() if len(found) > 1}


def beside(spark: SparkSession, sf_dir: str, name: str, predicates: Iterable[str]) -> DataFrame:
    """A table's subject as row_key and the object of each predicate as a column."""
    subject, made = _spec()[name]
    return table(spark, sf_dir, name).select(subject().alias("row_key"), *[made[p]().alias(p) for p in predicates]).where("row_key is not null")


def counts(spark: SparkSession, sf_dir: str, tables: Iterable[str] = CORE) -> dict[str, int]:
    return {name: table(spark, sf_dir, name).count() for name in tables}


def sizes(rows: Mapping[str, int]) -> dict[str, int]:
    """Triples of each predicate at most, from the tables' counts of rows."""
    out: dict[str, int] = {}
    for name, n in rows.items():
        for p in (*_spec()[name][1], *(("supplies", "contains") if name == "lineitem" else ())):
            out[p] = out.get(p, 0) + n
    return out


SEGMENTS = ("Automobile", "Building", "Furniture", "Household", "Machinery")
PRIORITIES = ("Urgent", "High", "Medium", "NotSpecified", "Low")
KINDS = ("Economy", "Large", "Medium", "Promo", "Small", "Standard")
#: Subclass, subproperty, transitive and inverse axioms.
AXIOMS: tuple[tuple[str, str, str], ...] = (
    *((f"{x}Customer", "subClassOf", "Customer") for x in SEGMENTS),
    *((f"{x}Order", "subClassOf", "Order") for x in PRIORITIES),
    *((f"{x}Part", "subClassOf", "Part") for x in KINDS),
    ("Customer", "subClassOf", "Party"), ("Supplier", "subClassOf", "Party"), ("Region", "subClassOf", "Place"), ("Nation", "subClassOf", "Place"),
    ("inNation", "subPropertyOf", "within"), ("inRegion", "subPropertyOf", "within"), ("within", "isTransitive", "true"),
    ("hosts", "inverseOf", "inNation"), ("placed", "inverseOf", "placedBy"),
)


def axioms(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(AXIOMS), "s string, p string, o string")
