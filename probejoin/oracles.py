"""DuckDB SQL over the given tables for graph patterns, written apart from the engine."""

from __future__ import annotations

from collections.abc import Sequence

from probejoin.plans.patterns import GraphPattern, TriplePattern, is_var

_LINE = "'line/' || l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey || '-' || CAST(l_extendedprice AS DECIMAL(18,2))"


def _lit(x: str) -> str:
    return f"'\"' || {x} || '\"'"


def _money(x: str) -> str:
    return _lit(f"CAST({x} AS DECIMAL(18,2))")


def _date(x: str) -> str:
    return _lit(f"strftime({x}, '%Y-%m-%d')")


_C, _S, _N, _R, _P, _O = "'customer/' || c_custkey", "'supplier/' || s_suppkey", "'nation/' || n_nationkey", "'region/' || r_regionkey", "'part/' || p_partkey", "'order/' || o_orderkey"


def _rows(s: str, o: str, table: str) -> str:
    return f"SELECT {s} AS s, {o} AS o FROM {table}"


_CUSTOMER_CLASS = "upper(c_mktsegment[1]) || lower(c_mktsegment[2:]) || 'Customer'"
_PART_CLASS = "upper(p_type[1]) || lower(p_type[2:]) || 'Part'"
_ORDER_CLASS = "CASE o_orderpriority WHEN '1-URGENT' THEN 'UrgentOrder' WHEN '2-HIGH' THEN 'HighOrder' WHEN '3-MEDIUM' THEN 'MediumOrder' WHEN '4-NOT SPECIFIED' THEN 'NotSpecifiedOrder' ELSE 'LowOrder' END"
#: Asserted triples of each predicate.
ASSERTED: dict[str, list[str]] = {
    "name": [_rows(_R, _lit("r_name"), "region"), _rows(_N, _lit("n_name"), "nation"), _rows(_C, _lit("c_name"), "customer"), _rows(_S, _lit("s_name"), "supplier"), _rows(_P, _lit("p_name"), "part")],
    "inRegion": [_rows(_N, "'region/' || n_regionkey", "nation")],
    "acctbal": [_rows(_C, _money("c_acctbal"), "customer"), _rows(_S, _money("s_acctbal"), "supplier")],
    "segment": [_rows(_C, _lit("c_mktsegment"), "customer")],
    "inNation": [_rows(_C, "'nation/' || c_nationkey", "customer"), _rows(_S, "'nation/' || s_nationkey", "supplier")],
    "brand": [_rows(_P, _lit("p_brand"), "part")],
    "kind": [_rows(_P, _lit("p_type"), "part")],
    "size": [_rows(_P, _lit("p_size"), "part")],
    "retailprice": [_rows(_P, _money("p_retailprice"), "part")],
    "placedBy": [_rows(_O, "'customer/' || o_custkey", "orders")],
    "status": [_rows(_O, _lit("o_orderstatus"), "orders")],
    "totalprice": [_rows(_O, _money("o_totalprice"), "orders")],
    "orderdate": [_rows(_O, _date("o_orderdate"), "orders")],
    "priority": [_rows(_O, _lit("o_orderpriority"), "orders")],
    "ofOrder": [_rows(_LINE, "'order/' || l_orderkey", "lineitem")],
    "ofPart": [_rows(_LINE, "'part/' || l_partkey", "lineitem")],
    "suppliedBy": [_rows(_LINE, "'supplier/' || l_suppkey", "lineitem")],
    "lineno": [_rows(_LINE, _lit("l_linenumber"), "lineitem")],
    "quantity": [_rows(_LINE, _money("l_quantity"), "lineitem")],
    "extendedprice": [_rows(_LINE, _money("l_extendedprice"), "lineitem")],
    "discount": [_rows(_LINE, _money("l_discount"), "lineitem")],
    "tax": [_rows(_LINE, _money("l_tax"), "lineitem")],
    "returnflag": [_rows(_LINE, _lit("l_returnflag"), "lineitem")],
    "linestatus": [_rows(_LINE, _lit("l_linestatus"), "lineitem")],
    "shipdate": [_rows(_LINE, _date("l_shipdate"), "lineitem")],
    "supplies": ["SELECT DISTINCT 'supplier/' || l_suppkey AS s, 'part/' || l_partkey AS o FROM lineitem"],
    "contains": ["SELECT DISTINCT 'order/' || l_orderkey AS s, 'part/' || l_partkey AS o FROM lineitem"],
    "rdf:type": [_rows(_R, "'Region'", "region"), _rows(_N, "'Nation'", "nation"), _rows(_C, _CUSTOMER_CLASS, "customer"), _rows(_S, "'Supplier'", "supplier"), _rows(_P, _PART_CLASS, "part"), _rows(_O, _ORDER_CLASS, "orders"), _rows(_LINE, "'LineItem'", "lineitem")],
}
#: What the axioms add.
INFERRED: dict[str, list[str]] = {
    "rdf:type": [_rows(_R, "'Place'", "region"), _rows(_N, "'Place'", "nation"), _rows(_C, "'Customer'", "customer"), _rows(_C, "'Party'", "customer"), _rows(_S, "'Party'", "supplier"), _rows(_P, "'Part'", "part"), _rows(_O, "'Order'", "orders")],
    "within": [
        _rows(_C, "'nation/' || c_nationkey", "customer"), _rows(_S, "'nation/' || s_nationkey", "supplier"), _rows(_N, "'region/' || n_regionkey", "nation"),
        "SELECT 'customer/' || c_custkey AS s, 'region/' || n_regionkey AS o FROM customer JOIN nation ON c_nationkey = n_nationkey",
        "SELECT 'supplier/' || s_suppkey AS s, 'region/' || n_regionkey AS o FROM supplier JOIN nation ON s_nationkey = n_nationkey",
    ],
    "hosts": [_rows("'nation/' || c_nationkey", _C, "customer"), _rows("'nation/' || s_nationkey", _S, "supplier")],
    "placed": [_rows("'customer/' || o_custkey", _O, "orders")],
}
PREDICATES = tuple(dict.fromkeys([*ASSERTED, *INFERRED]))


def of(p: str, inferred: bool = True) -> str:
    """Rows (s, o) of one predicate."""
    return " UNION ALL ".join([*ASSERTED.get(p, []), *(INFERRED.get(p, []) if inferred else [])])


def everything(inferred: bool = True) -> str:
    """Rows (s, p, o) of all predicates."""
    return " UNION ALL ".join(f"SELECT s, '{p}' AS p, o FROM ({of(p, inferred)})" for p in PREDICATES if of(p, inferred))


def _sql(term: str) -> str:
    return "'" + term.replace("'", "''") + "'"


def match(patterns: Sequence[TriplePattern], select: Sequence[str] = ()) -> str:
    """SQL for a basic graph pattern: one derived table for each pattern, equalities between them."""
    tables, where, where_of = [], [], {}
    for i, p in enumerate(patterns):
        if is_var(p.p):
            tables.append(f"({everything()}) t{i}")
        else:
            tables.append(f"(SELECT s, '{p.p}' AS p, o FROM ({of(p.p)})) t{i}")
        for k in "spo":
            term, column = p.at(k), f"t{i}.{k}"
            if not is_var(term):
                where.append(f"{column} = {_sql(term)}")
            elif term in where_of:
                where.append(f"{column} = {where_of[term]}")
            else:
                where_of[term] = column
    names = list(select) or [v[1:] for v in where_of]
    columns = ", ".join(f"{where_of['?' + n]} AS {n}" for n in names) or "true AS _found"
    return f"SELECT {columns} FROM {', '.join(tables)}" + (f" WHERE {' AND '.join(where)}" if where else "")


def answer(gp: GraphPattern) -> str:
    from probejoin.plans.planner import fold_filters

    folded = fold_filters(gp)
    return match(folded.patterns, folded.select)


def counted(sql: str, **facts: object) -> str:
    shown = ", ".join(f"{_sql(v) if isinstance(v, str) else v} AS {k}" for k, v in facts.items())
    return f"SELECT {shown}, count(*) AS value FROM ({sql}) x"
