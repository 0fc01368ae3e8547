"""Corpus pipeline: quality, near-duplicates, secrets, source mix, packing.

Each stage gets the documents its predecessor kept, written and read again, and all but the last
return the columns of ``documents`` (doc_id, text, lang, source, n_chars); others are ignored.

Defined results: an empty table passes through every stage. Null and blank texts pass the quality stage by
their score like any others, are nobody's near-duplicates and hold no secrets; having no words, they are
not part of the mix and end there. Rows with a null doc_id are documents of their own in all stages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rippletide.llm import cotrain
from rippletide.llm.odd_sketch import near_duplicates
from rippletide.llm.packing import pack
from rippletide.llm.scratch import stored
from rippletide.llm.secret_scan import find_secrets, redact
from rippletide.llm.source_mix import mix

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier rejects go; all others stay as they are."""
    model = cotrain.learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = cotrain.classify(docs, model, keep=["text", "lang", "source", "n_chars"])
    return scored.where("accepted").select(*COLUMNS)


def near_duplicate_groups(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity 0.8) the smallest doc_id stays; of
    its rows those equal in text collapse. Rows with a null doc_id stay."""
    groups = near_duplicates(docs, shingle=5, percent=80)
    gone = groups.where("doc_id is not null and not kept").select("doc_id").distinct()
    kept = docs.join(gone, "doc_id", "left_anti").select(*COLUMNS)
    return kept.where("doc_id is not null").dropDuplicates(["doc_id", "text"]).unionByName(kept.where("doc_id is null"))


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Live-looking secrets are replaced by a mark; widely copied examples stay."""
    found = find_secrets(docs, keep=["text", "lang", "source", "n_chars"])
    clean = F.when(F.col("n_live") > 0, redact(F.coalesce("text", F.lit("")), F.col("found"))).otherwise(F.col("text"))
    rows = found.select("doc_id", clean.alias("text"), "lang", "source", "n_chars", "n_live")
    return rows.withColumn("n_chars", F.when(F.col("n_live") > 0, F.length("text")).otherwise(F.col("n_chars")).cast("long")).select(*COLUMNS)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents by the words the mix takes of them: whole as often as it repeats them, and once in
    part where a quota ends inside; none of those without words."""
    taken = mix(docs, keep=["text", "lang", "source", "n_chars"])
    whole = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size"))).otherwise(F.lit(0))
    rest = F.col("taken") - whole * F.col("size")
    words = F.slice(F.split(F.trim(F.regexp_replace("text", "[\\x20\\x09-\\x0D]+", " ")), " "), F.lit(1), F.greatest(rest, F.lit(1)).cast("int"))
    part = F.concat_ws(" ", words)
    copies = F.concat(F.array_repeat(F.col("text"), whole.cast("int")), F.when(rest > 0, F.array(part)).otherwise(F.array().cast("array<string>")))
    rows = taken.select("doc_id", F.explode(copies).alias("text"), "lang", "source")
    return rows.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs)


STAGES = [
    ("quality classifier", quality),
    ("near-duplicates", near_duplicate_groups),
    ("secret scan", secrets),
    ("source mix", source_mix),
    ("packing", packing),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs, "stage")
    return docs
