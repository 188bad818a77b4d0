"""The experiment workloads as graph patterns over the given tables."""

from __future__ import annotations

from probejoin.plans.patterns import GraphPattern, bgp

T = "rdf:type"
WORKLOADS: dict[str, GraphPattern] = {
    "l1": bgp(f"?x {T} UrgentOrder", "?x placedBy customer/7", select=("x",)),
    "l3": bgp(f"?x {T} LineItem", "?x ofPart part/7", select=("x",)),
    "l4": bgp(f"?x {T} Customer", "?x inNation nation/3", "?x name ?y1", "?x acctbal ?y2", "?x segment ?y3", select=("x", "y1", "y2", "y3")),
    "l5": bgp(f"?x {T} Party", "?x within nation/3", select=("x",)),
    "l6": bgp(f"?x {T} Customer", select=("x",)),
    "l7": bgp(f"?x {T} Order", f"?y {T} Part", "?x contains ?y", "supplier/3 supplies ?y", select=("x", "y")),
    "l8": bgp(f"?x {T} Customer", f"?y {T} Nation", "?x inNation ?y", "?y within region/1", "?x name ?z", select=("x", "y", "z")),
    "l11": bgp(f"?x {T} Supplier", "?x within region/1", select=("x",)),
    "l13": bgp(f"?x {T} Party", "nation/3 hosts ?x", select=("x",)),
    "l14": bgp(f"?x {T} LineItem", select=("x",)),
    "s1": bgp(f"?x {T} Supplier", '?x name "Supplier#000000003"', "?x acctbal ?y", select=("x", "y")),
    "s2": bgp(f"?x {T} LineItem", "?x ofOrder ?a", "?x ofPart ?b", "?x suppliedBy ?c", "?x quantity ?d", "?x extendedprice ?e", "?x discount ?f", "?x returnflag ?g", "?x shipdate ?h", select=("x", "a", "b", "c", "d", "e", "f", "g", "h")),
    "s3a": GraphPattern(bgp(f"?x {T} Order", "?x ?pr ?v").patterns, ("x", "v"), filters=(("?pr", "=", "orderdate"),)),
    "s10": bgp("?s ?pr part/7", select=("s", "pr")),
    "x1": bgp(f"?x {T} Part", "?x name ?t", "?x brand ?b", "?x size ?y", select=("x", "t", "b", "y")),
    "x1plain": bgp("?x name ?t", "?x brand ?b", "?x size ?y", select=("x", "t", "b", "y")),
    "x2": bgp("?l ofOrder ?o", "?o placedBy ?c", "?c inNation ?n", "?n inRegion region/1", select=("l", "o", "c", "n")),
    "x4": bgp("supplier/3 supplies ?y", "?y brand ?b", select=("y", "b")),
}

#: Which ways each workload is run in.
VARIANTS: dict[str, tuple[str, ...]] = {
    **{k: ("cascade", "shuffle") for k in ("l1", "l3", "l5", "l11", "l13", "s3a", "l7", "l8", "x2", "x4")},
    **{k: ("cascade", "multiway", "row", "shuffle", "shuffle_star") for k in ("l4", "s1", "x1", "x1plain")},
    "s2": ("multiway", "row", "shuffle_star"),
    **{k: ("distributed", "local", "base_scan") for k in ("l6", "l14", "s10")},
}

#: One pattern of each shape.
SHAPES: dict[str, GraphPattern] = {
    "spo": bgp(f"customer/7 {T} Customer", select=()),
    "xpo": bgp("?s placedBy customer/7"),
    "sxo": bgp("order/5 ?p part/7"),
    "spx": bgp("order/5 placedBy ?o"),
    "xxo": bgp("?s ?p nation/3"),
    "xpx": bgp("?s inNation ?o"),
    "sxx": bgp("order/5 ?p ?o"),
    "xxx": bgp("?s ?p ?o"),
}

TEXTS: dict[str, tuple[str, str]] = {
    "l1": ("l1", f"SELECT ?x WHERE {{ ?x {T} UrgentOrder . ?x placedBy customer/7 }}"),
    "l4": ("l4", f"SELECT ?x ?y1 ?y2 ?y3 WHERE {{ ?x {T} Customer . ?x inNation nation/3 . ?x name ?y1 . ?x acctbal ?y2 . ?x segment ?y3 }}"),
    "l8": ("l8", f"SELECT ?x ?y ?z WHERE {{ ?x {T} Customer . ?y {T} Nation . ?x inNation ?y . ?y within region/1 . ?x name ?z }}"),
}
