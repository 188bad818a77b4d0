"""From graph patterns to plans: order, multiway groups, access, and the choice of a join."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.functions.terms import TYPE, decode
from probejoin.operators import probe, shuffle_baseline
from probejoin.operators.rowindex import IndexCatalog, named, units
from probejoin.plans import ordering
from probejoin.plans.access import OI, SI
from probejoin.plans.patterns import GraphPattern, Step, TriplePattern, is_var

#: Rows up to which a query of one pattern runs in one task, and outer mappings are looked up by literal keys.
LOCAL_ROWS, KEYED_ROWS = 10_000, 500


def fold_filters(gp: GraphPattern) -> GraphPattern:
    """Equality filters on a variable of predicate position become a constant of the pattern."""
    patterns, left = list(gp.patterns), []
    for var, op, term in gp.filters:
        if op == "=" and any(p.p == var for p in patterns) and not any(var in (p.s, p.o) for p in patterns):
            patterns = [TriplePattern(p.s, term if p.p == var else p.p, p.o) for p in patterns]
        else:
            left.append((var, op, term))
    return GraphPattern(tuple(patterns), gp.select, gp.distinct, tuple(left), gp.optional, gp.union, gp.order_by, gp.limit, gp.offset)


def extent(p: TriplePattern, stats: dict[str, dict]) -> float:
    """Estimated mappings of a pattern, from load-time counts under independence."""
    own = named((p.p, p.o))
    if own in stats:  # members of one class
        return stats[own]["n_triples"] / (1 if is_var(p.s) else max(stats[own]["n_subjects"], 1))
    rows = [stats[p.p]] if p.p in stats else [] if not is_var(p.p) else [r for k, r in stats.items() if " " not in k]
    total = 0.0
    for r in rows:
        n = float(r["n_triples"])
        n /= max(r["n_subjects"], 1) if not is_var(p.s) else 1
        n /= max(r["n_objects"], 1) if not is_var(p.o) else 1
        total += n
    return total


def joined_extent(patterns: Sequence[TriplePattern], stats: dict[str, dict]) -> float:
    """Estimated mappings of several patterns: their product, divided by the terms a variable may be at each further place it stands at."""
    total, terms = 1.0, {}
    for p in patterns:
        n = extent(p, stats)
        total *= n
        row = stats.get(named((p.p, p.o)), stats.get(p.p, {}))
        for k, column in (("s", "n_subjects"), ("p", ""), ("o", "n_objects")):
            if is_var(p.at(k)):
                terms.setdefault(p.at(k), []).append(max(1.0, min(n, float(row.get(column, n)))))
    for seen in terms.values():
        for n in sorted(seen)[1:]:
            total /= n
    return total


def order(patterns: Sequence[TriplePattern], mode: str = "connected", stats: dict[str, dict] | None = None) -> list[TriplePattern]:
    if mode == "stats":
        return ordering.connected(patterns, bound_aware=True, extent={str(p): extent(p, stats or {}) for p in patterns})
    if mode == "cheapest":
        return ordering.cheapest(patterns, lambda ps: joined_extent(ps, stats or {}))
    return ordering.MODES[mode](patterns)


def multiway_eligible(bound: Sequence[str], group: Sequence[TriplePattern]) -> bool:
    """Whether members share only variables that are bound already; else an extra equality is needed."""
    known = set(bound)
    for i, a in enumerate(group):
        for b in group[i + 1 :]:
            if (set(a.vars) & set(b.vars)) - known:
                return False
    return True


def row_eligible(var: str, bound: Sequence[str], group: Sequence[TriplePattern], compound: frozenset[str] = frozenset({TYPE})) -> str | None:
    """Index of which one row answers the whole group, if any."""
    if not multiway_eligible(bound, group) or any(is_var(p.p) for p in group):
        return None
    for place, far, index in (("s", "o", SI), ("o", "s", OI)):
        if all(p.position_of(var) == place for p in group):
            fresh = [p.at(far) for p in group if is_var(p.at(far))]
            if any(v[1:] in bound for v in fresh) or index == OI and any(p.p in compound for p in group):
                return None
            return index
    return None


def group_multiway(ordered: Sequence[TriplePattern]) -> list[list[TriplePattern]]:
    """Longest runs of patterns with one common variable that is bound where the run begins."""
    bound, at, out = set(ordered[0].vars), 1, []
    while at < len(ordered):
        best = at + 1
        for v in sorted(set(ordered[at].vars) & bound):
            end = at + 1
            while end < len(ordered) and v in ordered[end].vars:
                end += 1
            best = max(best, end)
        out.append(list(ordered[at:best]))
        bound |= {v for p in ordered[at:best] for v in p.vars}
        at = best
    return out


def plan(gp: GraphPattern, strategy: str = "cascade", mode: str = "connected", stats: dict[str, dict] | None = None, compound: frozenset[str] = frozenset({TYPE})) -> list[Step]:
    """Steps for the basic pattern. strategy: cascade, multiway (one lookup a pattern) or row (one lookup a mapping where one row answers)."""
    ordered = ordering.deferred(order(fold_filters(gp).patterns, mode, stats))
    steps = [Step("scan", [ordered[0]])]
    if len(ordered) == 1:
        return steps
    if strategy == "cascade":
        return steps + [Step("probe", [p]) for p in ordered[1:]]
    bound = list(ordered[0].vars)
    for group in group_multiway(ordered):
        shared = [v for v in bound if all(v in p.vars for p in group)]
        var = shared[0] if shared else None
        if len(group) == 1 or var is None:
            steps.append(Step("probe", group))
        else:
            index = row_eligible(var, bound, group, compound) if strategy == "row" else None
            notes = [] if multiway_eligible(bound, group) else ["extra equality"]
            steps.append(Step("row" if index else "multi", group, var, index, notes))
        bound += [v for p in group for v in p.vars if v not in bound]
    return steps


def run(idx: IndexCatalog, steps: Sequence[Step], join_mode: str = "auto") -> DataFrame:
    out = probe.read(idx, steps[0].patterns[0])
    for s in steps[1:]:
        if s.kind == "row":
            out = probe.row_multiway(idx, out, s.patterns, s.var, s.index)
        else:
            out = probe.multiway(idx, out, s.patterns, join_mode)
    return out


def choose_single(p: TriplePattern, stats: dict[str, dict], limit_rows: int = LOCAL_ROWS) -> str:
    return "local" if extent(p, stats) <= limit_rows else "distributed"


def choose_join(outer_rows: float, p: TriplePattern, stats: dict[str, dict], executors: int = 8) -> str:
    """keyed, broadcast, region or shuffle, by the rows each would move."""
    inner = extent(p, stats)
    cost = {
        "region": outer_rows + 0.1 * inner,
        "broadcast": outer_rows * executors + 0.05 * inner,
        "shuffle": outer_rows + inner,
    }
    if outer_rows <= KEYED_ROWS:
        cost["keyed"] = 50 + outer_rows
    return min(cost, key=cost.get)


def hybrid(idx: IndexCatalog, gp: GraphPattern) -> tuple[DataFrame, list[tuple[str, str]]]:
    """Each join by the cheapest way according to load-time statistics; the ways chosen come along."""
    stats = idx.stats(units(fold_filters(gp).patterns, idx.compound))
    ordered = order(fold_filters(gp).patterns, "stats", stats)
    out, rows, chosen = probe.read(idx, ordered[0]), extent(ordered[0], stats), []
    for p in ordered[1:]:
        way = choose_join(rows, p, stats)
        chosen.append((str(p), way))
        out = shuffle_baseline.step(out, idx.plain(units([p], idx.compound)), p) if way == "shuffle" else probe.step(out, idx, p, "auto" if way == "broadcast" else way)
        shared = [k for k in "so" if is_var(p.at(k)) and p.at(k)[1:] in out.columns]
        known = stats.get(named((p.p, p.o)), stats.get(p.p, {}))
        fan = known.get("n_triples", 1) / max(1, known.get("n_subjects", 1)) if shared else 1
        rows *= max(fan, 0.1)
    return out, chosen


_COMPARE = {"=": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, ">": lambda a, b: a > b, "<=": lambda a, b: a <= b, ">=": lambda a, b: a >= b}


def condition(var: str, op: str, term: str):
    """A comparison: terms by identity, numbers by value."""
    left = F.col(var[1:])
    number = term.strip('"').replace(".", "", 1).lstrip("-").isdigit()
    if is_var(term):
        return _COMPARE[op](left, F.col(term[1:]))
    if number and (op not in ("=", "!=") or not term.startswith('"')):
        return _COMPARE[op](decode(left, "decimal(38,6)"), F.lit(term.strip('"')).cast("decimal(38,6)"))
    return _COMPARE[op](left, F.lit(term))


def execute(idx: IndexCatalog, gp: GraphPattern, strategy: str = "cascade", mode: str = "connected", join_mode: str = "auto") -> DataFrame:
    """A whole query: basic pattern, unions, filters, optionals, then projection and modifiers."""
    gp = fold_filters(gp)
    every = [*gp.patterns, *(p for g in (*gp.union, *gp.optional) for p in g)]
    stats = idx.stats(units(every, idx.compound)) if mode == "stats" else None
    out = run(idx, plan(gp, strategy, mode, stats, idx.compound), join_mode) if gp.patterns else None
    if gp.union:
        parts = None
        for group in gp.union:
            part = run(idx, plan(GraphPattern(group), strategy, mode, stats, idx.compound), join_mode)
            parts = part if parts is None else parts.unionByName(part, allowMissingColumns=True)
        out = parts if out is None else out.join(parts, [c for c in out.columns if c in parts.columns])
    early = [f for f in gp.filters if f[0][1:] in out.columns and (not is_var(f[2]) or f[2][1:] in out.columns)]
    for f in early:
        out = out.where(condition(*f))
    for group in gp.optional:
        right = run(idx, plan(GraphPattern(group), strategy, mode, stats, idx.compound), join_mode)
        out = out.join(right, [c for c in out.columns if c in right.columns], "left")
    for f in gp.filters:
        if f not in early:
            out = out.where(condition(*f))
    out = out.select(*(gp.select or [v for v in gp.vars if v in out.columns]))
    if gp.distinct:
        out = out.distinct()
    if gp.order_by:
        out = out.orderBy(*[F.col(v).asc_nulls_first() if up else F.col(v).desc_nulls_last() for v, up in gp.order_by])
    if gp.offset:
        out = out.offset(gp.offset)
    return out if gp.limit is None else out.limit(gp.limit)


def explain(steps: Sequence[Step]) -> str:
    return "\n".join(f"{i}. {s}" + (f" [{', '.join(s.notes)}]" if s.notes else "") for i, s in enumerate(steps, 1))


