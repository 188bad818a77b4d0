"""Orders of the patterns of a graph pattern."""

from __future__ import annotations

from collections.abc import Callable, Mapping, Sequence

from probejoin.plans.patterns import TriplePattern, is_var

#: A bound subject selects more than a bound object, that more than a bound predicate.
WEIGHT = {"s": 4, "o": 2, "p": 1}


def rank(p: TriplePattern, bound: frozenset[str] = frozenset()) -> tuple[int, int]:
    """Number of free variables, then the weight of the given positions, heaviest first."""
    free = [v for v in p.vars if v not in bound]
    given = [k for k in "spo" if not is_var(p.at(k)) or p.at(k)[1:] in bound]
    return len(free), -sum(WEIGHT[k] for k in given)


def identity(patterns: Sequence[TriplePattern]) -> list[TriplePattern]:
    return list(patterns)


def static(patterns: Sequence[TriplePattern]) -> list[TriplePattern]:
    """Ranked once; ties keep their order. May put patterns side by side that share nothing."""
    return sorted(patterns, key=rank)


def connected(patterns: Sequence[TriplePattern], bound_aware: bool = False, extent: Mapping[str, float] | None = None) -> list[TriplePattern]:
    """Greedily the best pattern that shares a variable with those chosen.

    bound_aware counts bound variables as given; extent gives estimated sizes, which then
    come before the rank.
    """
    left, out, bound = list(patterns), [], frozenset()
    while left:
        near = [p for p in left if set(p.vars) & bound or not p.vars] or left
        key = lambda p: ((extent or {}).get(str(p), 0.0), rank(p, bound if bound_aware else frozenset()))  # noqa: B023, E731
        best = min(near, key=key)
        left.remove(best)
        out.append(best)
        bound |= set(best.vars)
    return out


#: Patterns up to which all connected orders are compared.
MOST_COMPARED = 12


def cheapest(patterns: Sequence[TriplePattern], size: Callable[[Sequence[TriplePattern]], float]) -> list[TriplePattern]:
    """The connected order with the fewest mappings on the way, where size estimates those of a set of patterns.

    A set's best order is looked for once, so the work is with the number of sets; beyond
    MOST_COMPARED patterns the connected order is taken.
    """
    if len(patterns) > MOST_COMPARED:
        return connected(patterns, True)
    best: dict[frozenset[int], tuple[float, list[int]]] = {frozenset([i]): (size([p]), [i]) for i, p in enumerate(patterns)}
    for _ in patterns[1:]:
        longer: dict[frozenset[int], tuple[float, list[int]]] = {}
        for chosen, (cost, places) in best.items():
            bound = {v for i in chosen for v in patterns[i].vars}
            left = [i for i in range(len(patterns)) if i not in chosen]
            for i in [i for i in left if set(patterns[i].vars) & bound or not patterns[i].vars] or left:
                both = chosen | {i}
                new = cost + size([patterns[k] for k in sorted(both)])
                if both not in longer or new < longer[both][0]:
                    longer[both] = new, [*places, i]
        best = longer
    return [patterns[i] for i in min(best.values())[1]]


def deferred(patterns: Sequence[TriplePattern]) -> list[TriplePattern]:
    """The same order, but a pattern that shares no variable with those before it waits until one of its variables is bound.

    So no product is formed that a later pattern would join; only patterns that nothing connects remain a product.
    """
    left, out, bound = list(patterns), [], set()
    while left:
        nxt = next((p for p in left if not bound or not p.vars or set(p.vars) & bound), left[0])
        left.remove(nxt)
        out.append(nxt)
        bound |= set(nxt.vars)
    return out


def variable_count(patterns: Sequence[TriplePattern], connected_order: bool = True) -> list[TriplePattern]:
    return connected(patterns) if connected_order else static(patterns)


MODES = {
    "identity": identity,
    "static": static,
    "connected": connected,
    "bound_aware": lambda ps: connected(ps, bound_aware=True),
}
