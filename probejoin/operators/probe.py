"""Index-probe joins: read patterns from the indexes and join mappings with them.

Mappings are rows with a column for each variable. A probe moves the mappings to the index
(or sends them to every task where they are few) and never the index.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.operators.rowindex import IndexCatalog, units
from probejoin.plans.access import OI, SI, choose
from probejoin.plans.ordering import deferred
from probejoin.plans.patterns import TriplePattern, is_var
from probejoin.sources.storage import written

#: Keys that may come to the driver and go back as literals.
MOST_KEYS = 1000


def read(idx: IndexCatalog, p: TriplePattern, index: str | None = None) -> DataFrame:
    """Mappings of a pattern; constants become partition, bucket or value filters of the scan."""
    path = choose(p, prefer=index, compound=idx.compound)
    which = index if index and (path.index == index or not is_var(p.s) or not is_var(p.o)) and (index == path.index or is_var(p.s) and is_var(p.o)) else path.index
    cells = idx.table(which, units([p], idx.compound))
    plain_key = which == OI and not is_var(p.p) and p.p not in idx.compound
    s, o = ("row_key", "value") if which == SI else ("value", "row_key" if plain_key else "o")
    for term, column in ((p.s, s), (p.p, "p"), (p.o, o)):
        if not is_var(term):
            cells = cells.where(F.col(column) == term)
    places: dict[str, list[str]] = {}
    for term, column in ((p.s, s), (p.p, "p"), (p.o, o)):
        if is_var(term):
            places.setdefault(term[1:], []).append(column)
    for columns in places.values():  # a variable that stands twice
        for other in columns[1:]:
            cells = cells.where(F.col(columns[0]) == F.col(other))
    return cells.select(*[F.col(columns[0]).alias(v) for v, columns in places.items()]) if places else cells.select(F.lit(True).alias("_found")).limit(1)


def index_for(p: TriplePattern, shared: Sequence[str], compound: frozenset[str]) -> tuple[str, str]:
    """Index whose row key a shared variable is, and that variable; a class is not a key of the object index."""
    for v in shared:
        if "s" in p.position_of(v):
            return SI, v
    for v in shared:
        if "o" in p.position_of(v) and not is_var(p.p) and p.p not in compound:
            return OI, v
    return (OI if any("o" in p.position_of(v) for v in shared) else SI), shared[0]


def _existing(outer: DataFrame, found: DataFrame) -> DataFrame:
    """outer if the pattern without variables is there, else nothing."""
    return outer.crossJoin(found).drop("_found")


def step(outer: DataFrame, idx: IndexCatalog, p: TriplePattern, mode: str = "auto", how: str = "inner") -> DataFrame:
    """Join mappings with a pattern.

    No shared variable: product. No new variable: a check that keeps or drops mappings (the
    graph is a set). mode: auto leaves the physical join to the optimizer and its size
    checks; region hashes the mappings to the buckets; broadcast sends them to every task
    (only where their size is known to be small); keyed fetches their distinct keys, at most
    MOST_KEYS, and reads just those rows, beyond that it is region.
    """
    shared = [v for v in p.vars if v in outer.columns]
    new = [v for v in p.vars if v not in shared]
    if not p.vars:
        return _existing(outer, read(idx, p))
    if not shared:
        return outer.crossJoin(read(idx, p))
    index, key = index_for(p, shared, idx.compound)
    inner = read(idx, p, index)
    if mode == "keyed":
        keys = [r[0] for r in outer.select(key).distinct().limit(MOST_KEYS + 1).collect()]
        if len(keys) <= MOST_KEYS:
            inner = inner.where(F.col(key).isin(keys))
        else:
            mode = "region"
    if not new and how == "inner":
        inner = inner.hint("merge") if mode == "region" else inner
        return outer.join(inner, shared, "left_semi")
    if mode == "region":
        outer = outer.hint("shuffle_hash") if how == "inner" else outer
    elif mode == "broadcast" and how == "inner":
        outer = F.broadcast(outer)
    return outer.join(inner, shared, how).select(*outer.columns, *new)


def join2(idx: IndexCatalog, first: TriplePattern, second: TriplePattern, mode: str = "auto") -> DataFrame:
    """The base case: scan one pattern, probe the other."""
    return step(read(idx, first), idx, second, mode)


def cascade(idx: IndexCatalog, patterns: Sequence[TriplePattern], mode: str = "auto", materialize: str = "none") -> DataFrame:
    """Probe joins one after another, patterns that share nothing yet later; with materialize='parquet' each result is written as an iteration of its own."""
    first, *rest = deferred(patterns)
    out = read(idx, first)
    for p in rest:
        out = step(out, idx, p, mode)
        if materialize == "parquet":
            out = written(out, "mappings")
    return out


def multiway(idx: IndexCatalog, outer: DataFrame, patterns: Sequence[TriplePattern], mode: str = "auto") -> DataFrame:
    """Several patterns on one variable: joins on the same key, so the mappings move once.

    Members that share a further variable are compared on it as well, as each step joins on
    all variables known so far.
    """
    out = outer
    for p in patterns:
        out = step(out, idx, p, mode)
    return out


def assembled(idx: IndexCatalog, patterns: Sequence[TriplePattern], var: str, index: str) -> DataFrame:
    """One row for each key that answers all patterns: var and an array m<i> for each pattern with a variable.

    Grouping is by row key, as the table is bucketed, so nothing is exchanged.
    """
    far = "o" if index == SI else "s"
    wanted = sorted({p.p for p in patterns})
    cells = idx.table(index, units(patterns, idx.compound)).where(F.col("p").isin(wanted))
    made, checks = [], []
    for i, p in enumerate(patterns):
        hit = F.col("p") == p.p
        term = p.at(far)
        if is_var(term):
            made.append(F.collect_set(F.when(hit, F.col("value"))).alias(f"m{i}"))
            checks.append(F.size(f"m{i}") > 0)
        else:
            made.append(F.max(F.when(hit & (F.col("value") == term), F.lit(True))).alias(f"m{i}"))
            checks.append(F.col(f"m{i}").isNotNull())
    rows = cells.groupBy("row_key").agg(*made)
    for check in checks:
        rows = rows.where(check)
    return rows.withColumnRenamed("row_key", var)


def expanded(rows: DataFrame, patterns: Sequence[TriplePattern], index: str, keep: Sequence[str]) -> DataFrame:
    """The product of the arrays of assembled rows."""
    far = "o" if index == SI else "s"
    out, names = rows, list(keep)
    for i, p in enumerate(patterns):
        if is_var(p.at(far)):
            name = p.at(far)[1:]
            out = out.withColumn(name, F.explode(f"m{i}"))
            names.append(name)
    return out.select(*names)


def row_multiway(idx: IndexCatalog, outer: DataFrame, patterns: Sequence[TriplePattern], var: str, index: str) -> DataFrame:
    """All patterns from one row: a single lookup for each mapping."""
    rows = assembled(idx, patterns, var, index)
    joined = outer.join(rows, var)
    return expanded(joined, patterns, index, outer.columns)


def star_scan(idx: IndexCatalog, patterns: Sequence[TriplePattern], var: str, index: str = SI) -> DataFrame:
    """A whole star as one grouped scan: no probe at all."""
    return expanded(assembled(idx, patterns, var, index), patterns, index, [var])


def single(idx: IndexCatalog, p: TriplePattern, local: bool = False) -> DataFrame:
    """A query of one pattern, distributed or gathered into one task where its estimate is small."""
    got = read(idx, p)
    return got.coalesce(1) if local else got


def grouped_product(outer: DataFrame, idx: IndexCatalog, patterns: Sequence[TriplePattern], var: str) -> DataFrame:
    """Mapping by mapping merge of lists, the literal form of the multiway join: for fixtures, not for scale."""
    import pandas as pd

    tagged = None
    for i, p in enumerate(patterns):
        far = [v for v in p.vars if v != var]
        rows = read(idx, p, SI).select(F.col(var), F.lit(i).alias("_i"), (F.col(far[0]) if far else F.lit("")).alias("_x"))
        tagged = rows if tagged is None else tagged.unionByName(rows)
    names = [next((v for v in p.vars if v != var), None) for p in patterns]
    new = [n for n in names if n]
    schema = ", ".join(f"`{c}` string" for c in (*outer.columns, *new))

    def merge(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        lists = [right.loc[right["_i"] == i, "_x"].tolist() for i in range(len(patterns))]
        rows = [list(r) for r in left.itertuples(index=False)]
        for name, values in zip(names, lists, strict=True):
            rows = [r + ([v] if name else []) for r in rows for v in values]
        return pd.DataFrame(rows, columns=[*left.columns, *new], dtype=object)

    return outer.groupBy(var).cogroup(tagged.groupBy(var)).applyInPandas(merge, schema)
