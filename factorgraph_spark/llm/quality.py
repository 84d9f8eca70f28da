"""Quality rules: log-likelihood ratio of hashed n-grams between a trusted target and the raw corpus, beside fixed counts.

Words and word pairs are hashed into ``BUCKETS`` buckets. Two multinomials over the buckets are estimated: one from the trusted documents (at
most ``TRUSTED_DOCS`` of them, those of lowest hashes), one from every document of the corpus. A document's score is the mean, over its
n-grams, of the log ratio of the two, so long and short texts compare; it is kept if the score is at least ``threshold``. The model is an
array of BUCKETS numbers, whatever the corpus, and stands in the scoring expression as a literal: scoring shuffles nothing. Counting
shuffles one row per task and bucket.

All of it is DataFrame operations.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE

BUCKETS = 4096
TRUSTED_DOCS = 20_000
#: Added to every bucket's count, in parts of the mean count.
SMOOTHING = 0.1
#: Least mean log ratio of a kept document.
THRESHOLD = -0.05


def words_of(text: Column) -> Column:
    """Runs of characters other than ASCII white space; null has none."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), f"[{SPACE}]+"), "")


def bucket_of(hashed: Column, buckets: int = BUCKETS) -> Column:
    return F.pmod(hashed, F.lit(buckets)).cast("int")


def runs(words: Column, length: int) -> Column:
    """Every ``length`` neighbouring words as a struct w0, w1, ...; its hash is that of the words one after another."""
    n = F.greatest(F.size(words) - (length - 1), F.lit(0))
    return F.arrays_zip(*[F.slice(words, k + 1, n).alias(f"w{k}") for k in range(length)])


def gram_counts(docs: DataFrame, text: str, buckets: int = BUCKETS) -> DataFrame:
    """bucket and n: how many words and pairs of neighbouring words of all texts fall into it.

    A row per word, next to its follower, is split into the two buckets by generated code: lambdas over arrays are interpreted, at four times
    the time.
    """
    words = docs.select(words_of(F.col(text)).alias("words"))
    at = words.select(F.explode(F.arrays_zip(F.col("words").alias("a"), F.slice("words", 2, F.size("words")).alias("b"))).alias("w"))
    two = F.when(F.col("w.b").isNotNull(), bucket_of(F.xxhash64("w.a", "w.b"), buckets))
    grams = at.select(F.explode(F.array(bucket_of(F.xxhash64("w.a"), buckets), two)).alias("bucket"))
    return grams.where("bucket is not null").groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


def log_ratios(docs: DataFrame, trusted: DataFrame, *, doc_id: str = "doc_id", text: str = "text", buckets: int = BUCKETS) -> list[float]:
    """log(target / raw) of every bucket. trusted: ids of trusted documents; without any, all ratios are 0."""
    some = trusted.select(F.col(doc_id).alias("good")).where("good is not null").distinct().orderBy(F.xxhash64("good"), "good").limit(TRUSTED_DOCS)
    target = docs.join(F.broadcast(some), F.col(doc_id) == F.col("good"))
    counts, good = gram_counts(docs, text, buckets), gram_counts(target, text, buckets)
    raw, own = ({r["bucket"]: r["n"] for r in part.collect()} for part in (counts, good))  # buckets rows at most
    n_raw, n_own = sum(raw.values()), sum(own.values())
    if not n_own:
        return [0.0] * buckets

    def share(found: dict, total: int, k: int) -> float:
        extra = SMOOTHING * total / buckets
        return (found.get(k, 0) + extra) / (total + extra * buckets)

    return [math.log(share(own, n_own, k) / share(raw, n_raw, k)) for k in range(buckets)]


def score(words: Column, ratios: list[float]) -> Column:
    """Mean log ratio over the n-grams; 0 without words."""
    table = F.lit(ratios).cast("array<double>")
    add = lambda acc, w: acc + F.get(table, bucket_of(F.xxhash64(w), len(ratios)))
    total = F.aggregate(runs(words, 2), F.aggregate(words, F.lit(0.0), add), add)
    return F.when(F.size(words) > 0, total / (2 * F.size(words) - 1)).otherwise(F.lit(0.0))


def judge(docs: DataFrame, ratios: list[float], *, doc_id: str = "doc_id", text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """One row per input row: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, score, base_failed and kept.

    Null and empty texts have no words, so the base rules fail them. n_repeat_words counts the words in windows of three words that the text
    holds twice or more. Repeated rows are judged each; an empty table gives an empty result; other columns are not read.
    """
    # Each step refers to the one before more than once, or from within a lambda, and is a projection of its own.
    rows = docs.select(F.col(doc_id).alias("id"), F.coalesce(F.col(text), F.lit("")).alias("t")).withColumn("words", words_of(F.col("t")))
    n = F.size("words")
    rows = rows.withColumn("windows", F.transform(runs(F.col("words"), 3), lambda w: F.xxhash64(w)))
    repeats = F.size(F.array_distinct("windows")) < F.size("windows")
    placed = F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("i")))
    rows = rows.withColumn("placed", F.when(repeats, F.sort_array(placed)).otherwise(F.array().cast("array<struct<h: bigint, i: int>>")))
    # Equal windows stand next to each other after sorting.
    beside = lambda k, x: (F.get("placed", k - 1)["h"] == x["h"]) | (F.get("placed", k + 1)["h"] == x["h"])
    twice = F.filter("placed", lambda x, k: F.coalesce(beside(k, x), F.lit(False)))
    covered = F.array_distinct(F.flatten(F.transform(twice, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2))))
    lines = F.filter(F.split("t", "\n"), lambda line: line.rlike(f"[^{SPACE}]"))
    rows = rows.withColumn("lines", lines)
    rows = rows.select(
        F.col("id").alias(doc_id),
        n.cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        (F.size(F.split("t", "[#*$%&|<>]")) - 1).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.size(covered).cast("long").alias("n_repeat_words"),
        score(F.col("words"), ratios).alias("score"),
    )
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return rows.withColumn("base_failed", failed).withColumn("kept", ~failed & (F.col("score") >= threshold))


def op5(docs: DataFrame, labels: DataFrame) -> DataFrame:
    trusted = labels.where("quality = 1 and coalesce(toxic, 0) = 0")
    return judge(docs, log_ratios(docs, trusted))
