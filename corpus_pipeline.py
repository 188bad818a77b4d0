"""Cleaning pipeline over documents: five stages, each written and read again."""

from __future__ import annotations

import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probejoin.llm import bpe, decontam, jaccard, langid, sufdedup
from probejoin.llm.common import shared_folder, table

#: Share of a text's n-grams that its language must hold, against the share expected of unseen rows of that language;
#: below it none stands out, however many languages there are.
LEAST_KNOWN = 0.4
#: Words of a passage that must not occur twice: passages of over 50 words go.
PASSAGE_WORDS = 51
#: Bytes of text that a task of that stage holds at a time, for tables up to about a gigabyte.
PASSAGE_BLOCK = 2 << 20
#: Bytes of a shuffle that a task reads from that stage on where partitions are joined for it: what is fetched lies in memory.
TASK_BYTES = 16 << 20


def _plain(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs under names that clash with none an operator adds, and the new name of each column."""
    plain = docs.toDF(*[f"c{k}" for k in range(len(docs.columns))])
    return plain, dict(zip(docs.columns, plain.columns, strict=True))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text has a language; those without letters or without a language that stands out go."""
    plain, name = _plain(docs)
    model = langid.train(langid.training_rows(plain, name["doc_id"]), name["text"], name["lang"])
    found = langid.predict(plain, model, name["doc_id"], name["text"], keep=True)
    kept = found.where((F.col("lang_pred") != langid.UNDECIDED) & (F.col("known") >= LEAST_KNOWN))
    return kept.select(*plain.columns).toDF(*docs.columns)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one of the smallest id. Rows that repeat that id and text stay one."""
    plain, name = _plain(docs)
    doc_id, text = name["doc_id"], name["text"]
    found = jaccard.join(plain, doc_id, text)
    kept = found.where(F.col(doc_id).eqNullSafe(F.col("component_id"))).select(F.col(doc_id).alias("kept_id")).distinct()
    rows = plain.join(kept, F.col(doc_id).eqNullSafe(F.col("kept_id")), "left_semi").withColumn("h", F.xxhash64(text))
    return rows.dropDuplicates([doc_id, "h"]).drop("h").toDF(*docs.columns)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages of over 50 words, however few their bytes, and byte strings of 400, however few their words, that occur elsewhere.

    A text of which nothing is left goes. n_chars follows the text, other columns stay.
    """
    spark.conf.set("spark.sql.adaptive.advisoryPartitionSizeInBytes", str(TASK_BYTES))
    plain, name = _plain(docs)
    rest = [c for c in plain.columns if c not in (name["text"], name["n_chars"])]
    rows = plain.select(F.struct(*rest).alias("row"), F.col(name["text"]).alias("text"))
    cut = sufdedup.repeats(rows, "row", "text", block_bytes=PASSAGE_BLOCK, texts=True, words=PASSAGE_WORDS)
    length = F.char_length("text").cast(docs.schema["n_chars"].dataType)
    got = {name["text"]: F.col("text"), name["n_chars"]: length}
    kept = _decoded(cut).where(F.char_length("text") > 0)
    return kept.select(*[got.get(c, F.col(f"row.{c}")).alias(c) for c in plain.columns]).toDF(*docs.columns)


def _decoded(cut: DataFrame) -> DataFrame:
    """Kept bytes as text; a cut inside a character leaves an incomplete one, which is dropped."""
    rows = cut.select(F.col(cut.columns[0]).alias("row"), "kept")
    schema = rows.select("row", F.lit("").alias("text")).schema

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([k.decode("utf-8", "ignore") for k in batch.column(1).to_pylist()], pa.string())], ["row", "text"])

    return rows.mapInArrow(run, schema)


def benchmark_free(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of what is left."""
    return bpe.encode(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("language", language), ("near copies", near_copies), ("repeated passages", repeated_passages), ("benchmark", benchmark_free), ("encode", encoded)]

#: SQL can't express the language filters, the edits of the benchmark stage or the encoding.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            path = shared_folder(spark, f"stage{k}")
            docs.write.option("compression", "zstd").parquet(path)
            docs = spark.read.parquet(path)
    return docs
