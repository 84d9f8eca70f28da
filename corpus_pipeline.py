"""A corpus from language identification to packed sequences, each stage an operator of the subpackage ``llm``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorgraph_spark.llm import langid, mixture, neardup, packing, secret_scan
from factorgraph_spark.llm.common import cut, fresh_path, landed, table
from factorgraph_spark.shipping import ship


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter and those whose language is uncertain."""
    ship(spark)
    return langid.accept(docs, langid.train(docs))


#: Column that numbers rows while near copies are sought.
KEY = "_near_duplicates_key"


def _numbered(docs: DataFrame) -> DataFrame:
    """docs with KEY: the doc_id where it is a row's own; rows without one or with a repeated one land in the shared folder with numbers beyond."""
    spark, found = docs.sparkSession, docs.groupBy("doc_id").count().where("doc_id is null or count > 1").select("doc_id")
    found = cut(found)
    plain = docs.withColumn(KEY, F.col("doc_id").cast("long"))
    if not found.limit(1).count():
        return plain
    repeated, known = found.where("doc_id is not null"), docs.where("doc_id is not null")
    low, top = docs.agg(F.min("doc_id"), F.max("doc_id")).first()
    number = F.lit(low - 1) - F.monotonically_increasing_id() if (top or 0) >= 1 << 62 else F.lit((top or 0) + 1) + F.monotonically_increasing_id()
    odd = docs.where("doc_id is null").unionByName(neardup.restrict(known, repeated, "left_semi", "doc_id").select(docs.columns))
    odd, _ = landed(odd.withColumn(KEY, number), "repeated")
    return neardup.restrict(plain.where("doc_id is not null"), repeated, "left_anti", "doc_id").select(odd.columns).unionByName(odd)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group of near copies (five-word shingles, similarity 0.8): of least doc_id, or any of those that have none of their
    own. Rows without text or words stay."""
    ship(spark)
    rows = _numbered(docs)
    removed = neardup.link(rows, doc_id=KEY, width=5, percent=80).where("not kept").select(KEY)
    return neardup.restrict(rows, removed, "left_anti", KEY).select(docs.columns)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces secrets in the texts and counts their characters anew."""
    ship(spark)
    return secret_scan.redact(docs).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(docs.columns)


def source_mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes every document as often as the mix of sources asks for: not at all, once or twice."""
    ship(spark)
    return mixture.mix(docs)


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the documents into sequences: a row per piece."""
    ship(spark)
    return packing.pack(docs)


STAGES = [
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("secrets", secrets),
    ("source_mixture", source_mixture),
    ("packed_sequences", packed_sequences),
]

#: Segmentation models, minhash and a tokenizer are beyond SQL; the tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = fresh_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
