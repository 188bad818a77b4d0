"""Relational operators around graph queries: projections, filters, joins, aggregates, windows, sorts and sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from probejoin.functions.terms import decode

W = Window


# --- on mappings -------------------------------------------------------------------------


def project(df: DataFrame, variables: list[str] | str) -> DataFrame:
    """A bag: equal mappings stay as often as they are."""
    return df if variables == "*" else df.select(*variables)


def distinct(df: DataFrame, variables: list[str]) -> DataFrame:
    return df.select(*variables).distinct()


def bind(df: DataFrame, name: str, value: Column) -> DataFrame:
    return df.withColumn(name, value)


def decoded(df: DataFrame, kinds: dict[str, str]) -> DataFrame:
    """Literals of the named variables as typed columns."""
    return df.select(*[decode(F.col(c), kinds[c]).alias(c) if c in kinds else F.col(c) for c in df.columns])


def ask(df: DataFrame) -> DataFrame:
    """One row: whether there is any mapping. Only one row is looked for."""
    return df.limit(1).agg((F.count("*") > 0).alias("answer"))


def construct(df: DataFrame, template: list[tuple[str, str, str]]) -> DataFrame:
    """Triples from mappings, a set; terms with a question mark are variables."""
    term = lambda t: F.col(t[1:]) if t.startswith("?") else F.lit(t)
    made = F.explode(F.array(*[F.struct(term(s).alias("s"), term(p).alias("p"), term(o).alias("o")) for s, p, o in template])).alias("t")
    return df.select(made).select("t.s", "t.p", "t.o").distinct()


# --- joins -------------------------------------------------------------------------------


def hash_join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    return a.join(b.hint("shuffle_hash"), on, how)


def merge_join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    return a.join(b.hint("merge"), on, how)


def replicated_join(a: DataFrame, small: DataFrame, on, most_rows: int = 100_000) -> DataFrame:
    """Broadcast where counting shows that the small side is small; beyond that hash."""
    return a.join(F.broadcast(small), on) if small.limit(most_rows + 1).count() <= most_rows else hash_join(a, small, on)


def asof_join(left: DataFrame, right: DataFrame, by: list[str], ts: str, take: dict[str, str]) -> DataFrame:
    """For each left row the latest right row of the same key before it: one shuffle, one pass, no inequality join."""
    none = {c: F.lit(None).cast(right.schema[c].dataType) for c in take}
    a = left.select(*left.columns, F.lit(1).alias("_side"), *[none[c].alias(f"_{c}") for c in take])
    lacking = [c for c in left.columns if c not in [*by, ts]]
    b = right.select(*by, ts, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in lacking], F.lit(0).alias("_side"), *[F.col(c).alias(f"_{c}") for c in take])
    before = W.partitionBy(*by).orderBy(ts, F.col("_side").desc()).rowsBetween(W.unboundedPreceding, -1)
    last = a.unionByName(b).select("*", *[F.last(f"_{c}", ignorenulls=True).over(before).alias(new) for c, new in take.items()])
    return last.where("_side = 1").select(*left.columns, *take.values())


def interval_join(left: DataFrame, right: DataFrame, by: str, lts: str, rts: str, seconds: int) -> DataFrame:
    """Right rows within so many seconds after a left row of the same key.

    Time is cut into bins of that length and each left row meets two of them, so a hot key is
    spread over its bins.
    """
    bin_of = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / F.lit(seconds * 1_000_000))
    a = left.withColumn("_bin", F.explode(F.array(bin_of(lts), bin_of(lts) + 1)))
    b = right.withColumn("_bin", bin_of(rts))
    gap = F.unix_micros(F.col(rts).cast("timestamp")) - F.unix_micros(F.col(lts).cast("timestamp"))
    return a.join(b, [by, "_bin"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_bin")


def range_join(df: DataFrame, bands: DataFrame, value: str, low: str, high: str) -> DataFrame:
    """Rows with the band [low, high) that holds their value; bands are a small fixed table."""
    return df.join(F.broadcast(bands), (F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


# --- windows -----------------------------------------------------------------------------


def top_k(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(W.partitionBy(*by).orderBy(*order))).where(F.col("place") <= k)


def sessions(df: DataFrame, by: str, ts: str, tie: str, gap_seconds: int) -> DataFrame:
    """Session numbers per key: a new one after a gap."""
    order = W.partitionBy(by).orderBy(ts, tie)
    micros = F.unix_micros(F.col(ts).cast("timestamp"))
    gap = micros - F.lag(micros).over(order)
    return df.withColumn("_new", F.when(gap <= gap_seconds * 1_000_000, 0).otherwise(1)).withColumn("session", F.sum("_new").over(order)).drop("_new")
