"""Map-side merge joins: both inputs bucketed and sorted alike beforehand."""

from __future__ import annotations

import uuid
from collections.abc import Sequence

from pyspark.sql import DataFrame

from probejoin.operators import shuffle_baseline
from probejoin.plans.patterns import TriplePattern
from probejoin.sources.storage import shared_folder


def prepared(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """The preprocessing: a table bucketed and sorted by key."""
    name = f"merge_{uuid.uuid4().hex[:12]}"
    df.repartition(buckets, key).write.format("parquet").bucketBy(buckets, key).sortBy(key).option("path", shared_folder(df.sparkSession, name)).saveAsTable(name)
    return df.sparkSession.table(name)


def step(outer: DataFrame, triples: DataFrame, p: TriplePattern, buckets: int = 8) -> DataFrame:
    """Both sides are prepared for the shared variable, then merged without an exchange."""
    key = next(v for v in p.vars if v in outer.columns)
    shared = [v for v in p.vars if v in outer.columns]
    left, right = prepared(outer, key, buckets), prepared(shuffle_baseline.scan(triples, p), key, buckets)
    new = [v for v in p.vars if v not in shared]
    return left.join(right.hint("merge"), shared).select(*outer.columns, *new)


def join2(triples: DataFrame, first: TriplePattern, second: TriplePattern, buckets: int = 8) -> DataFrame:
    return step(shuffle_baseline.scan(triples, first), triples, second, buckets)


def cascade(triples: DataFrame, patterns: Sequence[TriplePattern], buckets: int = 8) -> DataFrame:
    """Each join's result is prepared anew for the next key, which is what such joins cost in a row."""
    out = shuffle_baseline.scan(triples, patterns[0])
    for p in patterns[1:]:
        out = step(out, triples, p, buckets)
    return out
