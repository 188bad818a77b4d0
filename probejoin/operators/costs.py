"""What plans cost: phases, lookups, intermediate results, rows moved, layout and selectivity."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.operators import probe, shuffle_baseline
from probejoin.operators.rowindex import IndexCatalog, units
from probejoin.plans.patterns import GraphPattern, Step, TriplePattern
from probejoin.plans.planner import plan


def phases(steps: Sequence[Step]) -> int:
    """Map iterations: one for each step after the scan, one for a scan alone."""
    return max(1, len(steps) - 1)


def phase_rows(spark, workloads: dict[str, GraphPattern]) -> DataFrame:
    rows = [(name, strategy, phases(plan(gp, strategy))) for name, gp in workloads.items() for strategy in ("cascade", "multiway")]
    return spark.createDataFrame(rows, "workload string, variant string, phases int")


def _count(df: DataFrame, **facts) -> DataFrame:
    return df.agg(F.count("*").alias("value")).select(*[F.lit(v).alias(k) for k, v in facts.items()], "value")


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def intermediate(idx: IndexCatalog, name: str, ordered: Sequence[TriplePattern]) -> DataFrame:
    """Rows (workload, step, value): mappings after the scan and after each join."""
    out, parts = probe.read(idx, ordered[0]), []
    for k in range(len(ordered)):
        out = out if k == 0 else probe.step(out, idx, ordered[k])
        parts.append(_count(out, workload=name, step=k))
    return _union(parts)


def lookups(idx: IndexCatalog, name: str, ordered: Sequence[TriplePattern], star: bool) -> DataFrame:
    """Rows (workload, variant, value): index requests of each variant.

    cascade asks for every intermediate mapping; multiway for every input mapping that met
    all earlier members; row once for each input mapping (only for stars).
    """
    sizes = intermediate(idx, name, ordered[:-1])
    parts = [sizes.agg(F.sum("value").alias("value")).select(F.lit(name).alias("workload"), F.lit("cascade").alias("variant"), "value")]
    if star:
        outer = probe.read(idx, ordered[0])
        met, counts = outer, []
        for p in ordered[1:]:
            counts.append(_count(met, workload=name))
            shared = [v for v in p.vars if v in met.columns]
            met = met.join(probe.read(idx, p).select(*shared).distinct(), shared, "left_semi")
        parts.append(_union(counts).groupBy("workload").agg(F.sum("value").alias("value")).select("workload", F.lit("multiway").alias("variant"), "value"))
        parts.append(_count(outer, workload=name, variant="row"))
    return _union(parts)


def rows_moved(idx: IndexCatalog, name: str, ordered: Sequence[TriplePattern]) -> DataFrame:
    """Rows (workload, variant, value): what a cascade and a star of reduce-side joins move, and what probes return and send."""
    sizes = intermediate(idx, name, ordered)
    last = len(ordered) - 1
    extents = [_count(shuffle_baseline.scan(idx.plain(units(ordered, idx.compound)), p), workload=name, step=k) for k, p in enumerate(ordered)]
    both = _union(extents)
    inputs = sizes.where(F.col("step") < last)
    row = lambda df, variant: df.agg(F.sum("value").alias("value")).select(F.lit(name).alias("workload"), F.lit(variant).alias("variant"), "value")
    return _union([row(inputs.unionByName(both.where("step > 0")), "shuffle cascade"), row(both, "shuffle star"), row(sizes.where("step > 0"), "probe returned"), row(inputs, "probe sent")])


def selectivity(idx: IndexCatalog, results: dict[str, DataFrame]) -> DataFrame:
    """Rows (workload, answers, triples)."""
    n = idx.triples.agg(F.count("*").alias("triples"))
    return _union([df.agg(F.count("*").alias("answers")).crossJoin(n).select(F.lit(k).alias("workload"), "answers", "triples") for k, df in results.items()])


def exchanges(df: DataFrame) -> int:
    """Exchanges in the physical plan, broadcasts not counted."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return sum(1 for line in text.splitlines() if "Exchange" in line and "Broadcast" not in line and "Reused" not in line)
