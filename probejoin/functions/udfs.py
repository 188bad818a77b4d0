"""User-defined functions: the forms that built-in functions stand in for, kept for checks and for users."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.StringType())
def term_kind_udf(term: pd.Series) -> pd.Series:
    """Vectorized form of terms.term_kind."""
    head = term.str.split("/", n=1).str[0]
    out = head.where(term.str.contains("/", regex=False), "name")
    return out.where(~term.str.startswith('"'), "literal")


@F.pandas_udf(T.LongType())
def mapping_product_size(n: pd.Series) -> int:
    """Product of the sizes of a row's cells: how many mappings its star has."""
    return int(n.prod())


def cogroup_join(left: DataFrame, right: DataFrame, key: str, schema: str) -> DataFrame:
    """Two-sided reduce-side join in its literal form."""

    def merge(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return a.merge(b, on=key)

    return left.groupBy(key).cogroup(right.groupBy(key)).applyInPandas(merge, schema)


def pattern_variables(spark: SparkSession, bodies: DataFrame) -> DataFrame:
    """Variables of each body of patterns, by a table function."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="variable: string")
    class Variables:
        def eval(self, body: str):
            import re

            for name in dict.fromkeys(re.findall(r"\?(\w+)", body)):
                yield (name,)

    spark.udtf.register("pattern_variables", Variables)
    return spark.sql("SELECT name, variable FROM {b}, LATERAL pattern_variables(body)", b=bodies)


#: Rows that the row-at-a-time form may hold in each worker.
MOST_PINNED = 10_000


def rowwise_lookup(spark: SparkSession, small_index: DataFrame, outer: DataFrame) -> DataFrame:
    """One lookup for each mapping in an index of at most MOST_PINNED rows: the printed loop, for fixtures only."""
    from pyspark.sql.functions import udtf

    rows = small_index.select("row_key", "value").limit(MOST_PINNED + 1).collect()
    if len(rows) > MOST_PINNED:
        raise ValueError("the index is too large to be pinned; use probe.step")
    cells: dict[str, list[str]] = {}
    for r in rows:
        cells.setdefault(r["row_key"], []).append(r["value"])

    @udtf(returnType="r: string")
    class Lookup:
        def eval(self, key: str):
            for value in cells.get(key, ()):
                yield (value,)

    spark.udtf.register("lookup_cells", Lookup)
    return spark.sql("SELECT row_key, n, r FROM {o}, LATERAL lookup_cells(n)", o=outer)
