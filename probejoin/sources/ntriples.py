"""Triples as lines of text: subject, predicate and object between blanks, a dot at the end."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probejoin.functions.terms import is_literal
from probejoin.sources.storage import shared_folder


def _written(term):
    escaped = F.regexp_replace(F.regexp_replace(F.regexp_replace(term.substr(F.lit(2), F.length(term) - 2), r"\\", r"\\\\"), '"', r'\\"'), "\n", r"\\n")
    return F.when(is_literal(term), F.concat(F.lit('"'), escaped, F.lit('"'))).otherwise(F.concat(F.lit("<"), term, F.lit(">")))


def write(triples: DataFrame, path: str) -> None:
    triples.select(F.concat_ws(" ", *[_written(F.col(c)) for c in "spo"], F.lit(".")).alias("value")).write.text(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """Lines that are no triples are left out."""
    form = r'^<([^>]*)>\s+<([^>]*)>\s+(<[^>]*>|"(?:[^"\\]|\\.)*")\s*\.\s*$'
    line = F.col("value")
    o = F.regexp_extract(line, form, 3)
    body = o.substr(F.lit(2), F.length(o) - 2)
    plain = F.regexp_replace(F.regexp_replace(F.regexp_replace(body, r"\\n", "\n"), r'\\"', '"'), r"\\\\", r"\\")
    return spark.read.text(path).where(line.rlike(form)).select(F.regexp_extract(line, form, 1).alias("s"), F.regexp_extract(line, form, 2).alias("p"), F.when(o.startswith("<"), body).otherwise(F.concat(F.lit('"'), plain, F.lit('"'))).alias("o"))


def roundtrip(triples: DataFrame) -> DataFrame:
    path = shared_folder(triples.sparkSession, "nt")
    write(triples, path)
    return read(triples.sparkSession, path)
