"""Content-addressed WARC archive.

Two tables: `payloads` holds each distinct payload once under its SHA-256, `records` holds
every record's exact header bytes and that address.
Reading joins them again: the digest of each stored payload is recomputed and must be its
address, the record is put together byte by byte, its header is parsed and its payload digest
compared. A record whose payload is gone or not what its digest says is read as not verified. Of records with equal payloads (of at least `revisit_from` bytes) the one with the
smallest id is a response, the others revisit it and carry no block.

Digests and headers are SQL expressions; no Python runs on executors. The groups of equal
payloads are summed up before the shuffle; the join back to the rows is on the digest, whose
large partitions Spark splits.

Rows: null payload counts as empty; a null id sorts last and is written as an empty string;
rows that repeat a smallest id with the same payload are all responses, as nothing tells
them apart; extra columns are ignored; an empty table gives an empty archive.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from probejoin.llm.common import shared_folder

ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"  # fixed values of base32


def base32(digest: Column) -> Column:
    """Upper-case base32 of a SHA-1 in hex: 160 bits are eight groups of four letters."""

    def letters(group: Column) -> Column:
        value = F.conv(F.substr(digest, group * F.lit(5) + F.lit(1), F.lit(5)), 16, 10).cast("int")
        return F.concat(*[F.substr(F.lit(ALPHABET), F.shiftright(value, s).bitwiseAND(F.lit(31)) + F.lit(1), F.lit(1)) for s in (15, 10, 5, 0)])

    return F.concat(*[letters(F.lit(k)) for k in range(8)])


def _header(kind: str) -> Column:
    """Header of a response or revisit record, as text with CRLF ends and the empty line."""
    id_text = F.coalesce(F.col("id").cast("string"), F.lit(""))
    lines = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.lit(kind)),
        F.concat(F.lit("WARC-Record-ID: <urn:record:"), id_text, F.lit(">")),
        F.concat(F.lit("WARC-Target-URI: "), F.regexp_replace(F.coalesce("url", F.lit("")), "[\r\n]", "")),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("payload_digest")),
    ]
    if kind == "revisit":
        lines += [F.concat(F.lit("WARC-Refers-To: <urn:record:"), F.coalesce(F.col("first").cast("string"), F.lit("")), F.lit(">")), F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")]
    lines += [F.lit("Content-Type: text/html; charset=utf-8"), F.concat(F.lit("Content-Length: "), F.when(F.lit(kind == "revisit"), F.lit("0")).otherwise(F.col("payload_bytes").cast("string")))]
    return F.concat(F.concat_ws("\r\n", *lines), F.lit("\r\n\r\n"))


def _table(folder: str) -> str:
    """Name under which a session knows an archive's payloads; other sessions read the files."""
    return "warc_payloads_" + hashlib.sha1(folder.encode()).hexdigest()[:16]


def _once(rows: DataFrame) -> DataFrame:
    """Each payload once, of whichever row, as equal addresses are equal bytes: payloads cross the network once, after a sum by task."""
    return rows.select("address", "payload").dropDuplicates(["address"])


def write(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", revisit_from: int = 0) -> None:
    """Write the archive below folder, which executors share."""
    payload = F.coalesce(F.col(payload_col).cast("binary"), F.lit("").cast("binary"))
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), payload.alias("payload")).select("*", F.unhex(F.sha2("payload", 256)).alias("address"), F.octet_length("payload").cast("long").alias("payload_bytes"))
    firsts = rows.groupBy("address").agg(F.min("id").alias("first"))
    marked = (
        rows.select("id", "url", "address", "payload_bytes", F.unhex(F.sha1("payload")).alias("sha1"))
        .join(firsts, "address")
        .withColumn("payload_digest", base32(F.lower(F.hex("sha1"))))
        .withColumn("revisits", (F.col("payload_bytes") >= revisit_from) & ~F.coalesce(F.col("id").eqNullSafe(F.col("first")), F.lit(False)))
    )
    records = marked.select("id", "address", F.when(F.col("revisits"), _header("revisit")).otherwise(_header("response")).cast("binary").alias("header"))
    records.write.option("compression", "zstd").parquet(f"{folder}/records")
    once = _once(rows)
    # bucketed as it lies after the aggregation, so that reading it does not move payloads again
    n = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    once.write.format("parquet").option("compression", "zstd").option("path", f"{folder}/payloads").bucketBy(n, "address").saveAsTable(_table(folder))


def read(spark, folder: str) -> DataFrame:
    """Records put together again: id, record_type, refers_to, payload_digest, payload_bytes, record (exact bytes), verified."""
    records = spark.read.parquet(f"{folder}/records")
    payloads = spark.table(_table(folder)) if spark.catalog.tableExists(_table(folder)) else spark.read.parquet(f"{folder}/payloads")
    text = F.col("header").cast("string")
    field = lambda name: F.regexp_extract(text, rf"\r\n{name}: ([^\r]*)\r\n", 1)
    id_type = records.schema["id"].dataType
    checked = payloads.select("address", "payload", (F.unhex(F.sha2("payload", 256)) == F.col("address")).alias("sound"), F.unhex(F.sha1("payload")).alias("sha1"))
    refers = F.regexp_extract(field("WARC-Refers-To"), "^<urn:record:(.*)>$", 1)
    return records.join(checked, "address", "left").select(
        "id",
        field("WARC-Type").alias("record_type"),
        F.when(field("WARC-Type") == "revisit", F.nullif(refers, F.lit("")).cast(id_type)).alias("refers_to"),
        F.regexp_extract(field("WARC-Payload-Digest"), "^sha1:(.*)$", 1).alias("payload_digest"),
        F.octet_length("payload").cast("long").alias("payload_bytes"),
        F.concat("header", F.when(field("WARC-Type") == "response", F.col("payload")).otherwise(F.lit("").cast("binary")), F.lit("\r\n\r\n").cast("binary")).alias("record"),
        F.coalesce(F.col("sound") & (base32(F.lower(F.hex("sha1"))) == F.regexp_extract(field("WARC-Payload-Digest"), "^sha1:(.*)$", 1)), F.lit(False)).alias("verified"),
    )


def archive(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", revisit_from: int = 0) -> DataFrame:
    """Write, read back, and give the digest columns of every record; raises if one is not as it was written."""
    spark = pages.sparkSession
    folder = shared_folder(spark, "warc")
    write(pages, folder, id_col, url_col, payload_col, revisit_from)
    got = read(spark, folder)
    lost = F.raise_error(F.concat(F.lit("record is not as it was written: "), F.coalesce(F.col("id").cast("string"), F.lit("null"))))
    size = F.when(F.col("verified"), F.col("payload_bytes")).otherwise(lost.cast("long"))
    return got.select(F.col("id").alias(id_col), size.alias("payload_bytes"), "payload_digest", "record_type", "refers_to")
