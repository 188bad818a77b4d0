"""Which index answers a triple pattern, how, and with which filters."""

from __future__ import annotations

from dataclasses import dataclass

from probejoin.functions.terms import TYPE
from probejoin.plans.patterns import TriplePattern, is_var

SI, OI = "SI", "OI"


@dataclass(frozen=True)
class AccessPath:
    index: str
    mode: str  # GET, RANGE, GET+RANGE or SCAN
    column_filter: bool
    value_filter: bool


def choose(p: TriplePattern, bound: frozenset[str] = frozenset(), prefer: str | None = None, compound: frozenset[str] = frozenset({TYPE})) -> AccessPath:
    """Path for a pattern, variables in bound counting as given.

    Where both indexes can answer, prefer decides, else the subject index. A class is spread
    over the rows of its members, so its object key is a range; with a free predicate it is
    both a row of its own and a range.
    """
    shape = p.shape(bound)
    spread = not is_var(p.p) and p.p in compound
    either = prefer or SI
    if shape == "spo":
        index = SI if spread and prefer is None else either
        return AccessPath(index, "GET", True, True)
    if shape == "?po":
        return AccessPath(OI, "RANGE" if spread else "GET", True, False)
    if shape == "s?o":
        return AccessPath(either, "GET" if either == SI else "GET+RANGE", False, True)
    if shape == "sp?":
        return AccessPath(SI, "GET", True, False)
    if shape == "??o":
        return AccessPath(OI, "GET+RANGE" if compound else "GET", False, False)
    if shape == "?p?":
        return AccessPath(either, "SCAN", True, False)
    if shape == "s??":
        return AccessPath(SI, "GET", False, False)
    return AccessPath(either, "SCAN", False, False)
