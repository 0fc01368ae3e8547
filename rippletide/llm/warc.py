"""Writing tables of pages to WARC archives and reading them back."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rippletide.llm.idbits import LOG_BITS
from rippletide.llm.scratch import fresh_path, stored
from rippletide.llm.skew import join_by_count
from rippletide.llm.warc_source import WarcDataSource


def register(spark: SparkSession) -> None:
    """Make the format ``warc`` known; the runtime setting lets predicates reach its reader."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcDataSource)


def _slot(key: Column) -> Column:
    return key.bitwiseXOR(F.shiftright(key, LOG_BITS)).bitwiseAND(F.lit((1 << LOG_BITS) - 1).cast("long"))


def _maybe(rows: DataFrame, keys: DataFrame) -> DataFrame:
    """``rows`` with ``maybe``: whether the page_id's bit is set in a bitmap of those of ``keys``, which is
    broadcast and has 2**LOG_BITS bits whatever the data hold."""
    bits = keys.groupBy(F.shiftright(_slot(F.col("page_id")), 6).alias("w")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast((page_id ^ shiftright(page_id, {LOG_BITS})) & 63 as int))")).alias("bits"))
    bit = F.expr(f"shiftrightunsigned(bits, cast((page_id ^ shiftright(page_id, {LOG_BITS})) & 63 as int)) & 1")
    return rows.withColumn("w", F.shiftright(_slot(F.col("page_id")), 6)).join(F.broadcast(bits), "w", "left").withColumn("maybe", F.coalesce(bit == 1, F.lit(False))).drop("w", "bits")


def with_revisits(pages: DataFrame, payload: str = "html", key: str = "page_id", least_bytes: int = 0) -> DataFrame:
    """page_id, url, payload, record_type, refers_to, payload_bytes, payload_digest: of equal payloads of
    at least ``least_bytes`` bytes the row with the smallest id is the response and the others revisit it.
    A revisit has no payload here, but its length and digest; a response has the payload only. Null
    payloads are empty; a row with a null id is always a response; rows repeating the smallest id are
    responses. Revisits are found on (id, digest) alone, and payloads are shuffled only where a bitmap
    says that the id may be a revisit's."""
    body = F.coalesce(F.col(payload).cast("string"), F.lit(""))
    url = F.col("url").cast("string") if "url" in pages.columns else F.lit(None).cast("string")
    rows = pages.select(F.col(key).cast("long").alias("page_id"), url.alias("url"), body.alias("payload"))
    digest = F.sha1(F.col("payload").cast("binary"))
    size = F.octet_length("payload").cast("long")
    heads = stored(rows.select("page_id", "url", size.alias("payload_bytes"), digest.alias("digest")).where(F.col("page_id").isNotNull() & (F.col("payload_bytes") >= least_bytes)), "heads")
    shared = stored(heads.groupBy("digest").agg(F.min("page_id").alias("first"), F.max("page_id").alias("last"), F.count(F.lit(1)).alias("c")).where("last > first").select("digest", "first", "c"), "shared")
    revisits = stored(join_by_count(heads, shared, ["digest"]).where("page_id > first"), "revisits")
    judged = _maybe(rows, revisits)
    exact = judged.where("maybe").withColumn("digest", digest).join(revisits.select("page_id", "digest").distinct(), ["page_id", "digest"], "left_anti")
    responses = judged.where("not maybe").select("page_id", "url", "payload").union(exact.select("page_id", "url", "payload"))
    return responses.select("page_id", "url", "payload", F.lit("response").alias("record_type"), *[F.lit(None).cast(t).alias(c) for c, t in (("refers_to", "long"), ("payload_bytes", "long"), ("payload_digest", "string"))]).unionByName(
        revisits.select("page_id", "url", F.lit(None).cast("string").alias("payload"), F.lit("revisit").alias("record_type"), F.col("first").alias("refers_to"), "payload_bytes", base32(F.col("digest")).alias("payload_digest"))
    )


def write_archives(records: DataFrame, path: str, compress: bool = True) -> None:
    register(records.sparkSession)
    records.write.format("warc").mode("append").option("compress", str(compress).lower()).save(path)


def read_archives(spark: SparkSession, path: str, payload: bool = True, only: dict[str, list] | None = None) -> DataFrame:
    """Records of the archives under ``path``; ``only`` keeps those whose header has one of the values
    listed for a column, before their payloads are touched."""
    register(spark)
    return spark.read.format("warc").options(payload=str(payload).lower(), only=json.dumps(only or {})).load(path)


def scan_archives(spark: SparkSession, path: str, where: str, payload: bool = True) -> DataFrame:
    """One query's records that satisfy ``where``, its header predicates pushed down by Spark. Do not
    build further filters on the result and use it again: load anew instead."""
    register(spark)
    return spark.read.format("warc").options(payload=str(payload).lower(), pushdown="true").load(path).where(where)


def round_trip(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Write ``pages``, read the archives back: page_id, payload_bytes, payload_digest, record_type,
    refers_to. A response's length and digest are of the payload as read; revisits are read by their
    headers alone."""
    spark = pages.sparkSession
    path = fresh_path(spark, "warc")
    write_archives(with_revisits(pages, least_bytes=least_bytes), path)
    answers = read_archives(spark, path, only={"record_type": ["response"]})
    again = read_archives(spark, path, payload=False, only={"record_type": ["revisit"]})
    length, digest = F.octet_length("payload").cast("long"), base32(F.sha1(F.col("payload").cast("binary")))
    return answers.select("page_id", length.alias("payload_bytes"), digest.alias("payload_digest"), "record_type", "refers_to").unionByName(again.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"))


def base32(hexed: Column) -> Column:
    """Upper-case base32 of a 40-digit hexadecimal string (20 bytes, so without padding): forty bits are
    eight digits of base 32."""
    digits = F.concat(*[F.lpad(F.conv(F.substring(hexed, 1 + 10 * i, 10), 16, 32), 8, "0") for i in range(4)])
    return F.translate(digits, "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")
