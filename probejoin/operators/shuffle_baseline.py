"""Reduce-side joins over the plain file of triples: everything that is joined is moved."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.plans.patterns import TriplePattern, is_var


def scan(triples: DataFrame, p: TriplePattern) -> DataFrame:
    """Mappings of a pattern from the un-indexed triples."""
    places: dict[str, list[str]] = {}
    for k in "spo":
        if is_var(p.at(k)):
            places.setdefault(p.at(k)[1:], []).append(k)
        else:
            triples = triples.where(F.col(k) == p.at(k))
    for columns in places.values():
        for other in columns[1:]:
            triples = triples.where(F.col(columns[0]) == F.col(other))
    return triples.select(*[F.col(c[0]).alias(v) for v, c in places.items()]) if places else triples.select(F.lit(True).alias("_found")).limit(1)


def step(outer: DataFrame, triples: DataFrame, p: TriplePattern, skew: str = "aqe", small: str | None = None) -> DataFrame:
    """Both sides are hashed by the shared variables and merged. small='broadcast' replicates the pattern instead, if Spark finds it small."""
    inner = scan(triples, p)
    if not p.vars:
        return outer.crossJoin(inner).drop("_found")
    shared = [v for v in p.vars if v in outer.columns]
    new = [v for v in p.vars if v not in shared]
    if not shared:
        return outer.crossJoin(inner)
    if skew == "salt":
        return salted(outer, inner, shared, new)
    if small is None:
        inner = inner.hint("merge")
    return outer.join(inner, shared).select(*outer.columns, *new)


def salted(outer: DataFrame, inner: DataFrame, shared: Sequence[str], new: Sequence[str], salts: int = 8) -> DataFrame:
    """The outer side of a key is dealt to several tasks, the inner side copied to each of them."""
    left = outer.withColumn("_salt", F.pmod(F.xxhash64(*outer.columns), F.lit(salts)))
    right = inner.withColumn("_salt", F.explode(F.array(*[F.lit(k).cast("long") for k in range(salts)])))
    return left.join(right.hint("merge"), [*shared, "_salt"]).select(*outer.columns, *new)


def join2(triples: DataFrame, first: TriplePattern, second: TriplePattern, **options) -> DataFrame:
    return step(scan(triples, first), triples, second, **options)


def cascade(triples: DataFrame, patterns: Sequence[TriplePattern], **options) -> DataFrame:
    out = scan(triples, patterns[0])
    for p in patterns[1:]:
        out = step(out, triples, p, **options)
    return out


def star(triples: DataFrame, patterns: Sequence[TriplePattern], var: str) -> DataFrame:
    """All patterns of a star in one shuffle: extents tagged, grouped by the variable, and their product taken.

    Patterns share no variable but var; each has at most one other.
    """
    tagged = None
    for i, p in enumerate(patterns):
        other = [v for v in p.vars if v != var]
        rows = scan(triples, p).select(F.col(var), F.lit(i).alias("tag"), (F.col(other[0]) if other else F.lit("")).alias("_x"))
        tagged = rows if tagged is None else tagged.unionByName(rows)
    lists = tagged.groupBy(var).agg(*[F.collect_list(F.when(F.col("tag") == i, F.col("_x"))).alias(f"m{i}") for i in range(len(patterns))])
    out, names = lists, [var]
    for i, p in enumerate(patterns):
        other = [v for v in p.vars if v != var]
        out = out.where(F.size(f"m{i}") > 0)
        if other:
            out = out.withColumn(other[0], F.explode(f"m{i}"))
            names.append(other[0])
    return out.select(*names)
