"""URL filter: longest-match rules, and gradient-boosted trees on lexical features for what no rule settles.

The trees are fitted by Spark's own DataFrame estimator on at most ``SAMPLE_URLS`` labelled URLs (those of lowest hashes), so that the model
does not depend on the size of the crawl; URLs are then scored where they are, without a shuffle. Labels come from the rules: a URL that a
rule settles is a labelled example. Host and path decide the rules, so no feature repeats a rule's text: features are lengths, depth, shares
of character classes, entropy, counts of parameters, and the statistics of the host's last label among the labelled URLs.

All of it is DataFrame operations; the estimator runs within Spark.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.ml.classification import GBTClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, lower_ascii

# Verdict, host and path of each rule.
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
#: Labelled URLs that the trees are fitted on; suffixes whose statistics are kept (the most frequent of the sample).
SAMPLE_URLS = 8_192
SUFFIXES = 256
TREES, DEPTH, SEED = 12, 4, 7
FEATURES = ("length", "host_length", "path_length", "depth", "host_labels", "digit_ratio", "symbol_ratio", "entropy", "parameters", "has_fragment", "secure", "longest_segment", "digits_in_path", "suffix_block", "suffix_seen")


@dataclass(frozen=True)
class Parts:
    host: Column
    path: Column


def split_url(url: Column) -> Parts:
    """Host (A-Z lower-cased) and path; both empty without "://"."""
    after = F.when(F.instr(url, "://") > 0, F.regexp_replace(url, r"(?s)^.*?://", "")).otherwise(F.lit(""))
    after = F.coalesce(after, F.lit(""))
    host = F.regexp_extract(after, r"(?s)^([^/?#]*)", 1)
    path = F.regexp_extract(after, r"(?s)^[^/?#]*([^?#]*)", 1)
    return Parts(lower_ascii(host), path)


def rule_column(host: Column, path: Column, rules=RULES) -> Column:
    """Struct of rule and verdict of the longest rule that fits; null if none does."""
    out = None
    for verdict, h, p in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r)):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        found = F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))
        out = F.when(fits, found) if out is None else out.when(fits, found)
    return out if out is not None else F.lit(None).cast("struct<rule: string, verdict: string>")


def _count(text: Column, characters: str) -> Column:
    return F.length(text) - F.length(F.translate(text, characters, ""))


def lexical(url: Column, host: Column, path: Column) -> dict[str, Column]:
    """The features of a URL that need no statistics."""
    n = F.greatest(F.length(url), F.lit(1))
    letters = F.split(url, "")
    share = lambda c: (F.length(url) - F.length(F.replace(url, c))) / n
    digits = "0123456789"
    query = F.regexp_extract(url, r"(?s)\?([^#]*)", 1)
    entropy = F.aggregate(F.array_distinct(F.filter(letters, lambda c: c != "")), F.lit(0.0), lambda acc, c: acc - share(c) * F.log2(share(c)))
    return {
        "length": F.length(url),
        "host_length": F.length(host),
        "path_length": F.length(path),
        "depth": _count(path, "/"),
        "host_labels": _count(host, ".") + 1,
        "digit_ratio": _count(url, digits) / n,
        "symbol_ratio": _count(url, "-_%~+!*$;,@") / n,
        "entropy": entropy,
        "parameters": F.when(query != "", _count(query, "&") + 1).otherwise(0),
        "has_fragment": F.contains(url, F.lit("#")),
        "secure": F.startswith(url, F.lit("https:")),
        "longest_segment": F.array_max(F.transform(F.split(path, "/"), lambda s: F.length(s))),
        "digits_in_path": _count(path, digits),
    }


def _features(rows: DataFrame, suffixes: dict[str, tuple[float, float]]) -> DataFrame:
    made = lexical(F.col("u"), F.col("host"), F.col("path"))
    last = F.element_at(F.split("host", r"\."), -1)
    lookup = lambda k: F.coalesce(F.try_element_at(F.create_map(*[F.lit(x) for s, v in suffixes.items() for x in (s, v[k])]), last), F.lit(0.5 if not k else 0.0)) if suffixes else F.lit(0.0)
    made |= {"suffix_block": lookup(0), "suffix_seen": lookup(1)}
    return rows.withColumns({f: F.coalesce(made[f].cast("double"), F.lit(0.0)) for f in FEATURES})


def fit(rows: DataFrame):
    """Trees and suffix statistics from rows (u, host, path, settled); None for the trees if the labels are all alike. Trees are fitted on at most
    SAMPLE_URLS different URLs; suffix statistics count all settled rows, of the SUFFIXES most frequent suffixes."""
    settled = rows.where("settled is not null").select("u", "host", "path", (F.col("settled.verdict") == "block").cast("double").alias("label"))
    each = settled.groupBy("u", "host", "path", "label").agg(F.count(F.lit(1)).alias("n"))  # a URL counts once, however many rows it has
    sample = cut(each.drop("n").orderBy(F.xxhash64("u"), "u").limit(SAMPLE_URLS).coalesce(1))
    last = F.element_at(F.split("host", r"\."), -1)
    kept = settled.groupBy(last.alias("s")).agg(F.sum("label").alias("b"), F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "s").limit(SUFFIXES).collect()
    total = sum(r["n"] for r in kept) or 1
    suffixes = {r["s"]: ((r["b"] + 1) / (r["n"] + 2), r["n"] / total) for r in kept if r["s"]}
    labels = sample.agg(F.min("label"), F.max("label")).first()
    if labels[0] is None or labels[0] == labels[1]:
        return None, suffixes, "block" if labels[0] else "allow"
    trees = GBTClassifier(featuresCol="x", labelCol="label", maxIter=TREES, maxDepth=DEPTH, seed=SEED, checkpointInterval=-1)
    ready = VectorAssembler(inputCols=list(FEATURES), outputCol="x").transform(_features(sample, suffixes)).select("x", "label")
    return trees.fit(ready), suffixes, ""


def judge(pages: DataFrame, *, page_id: str = "page_id", url: str = "url", rules=RULES, threshold: float = 0.5) -> DataFrame:
    """One row per input row: page_id, host, path, rule, verdict (allow or block) and p_block (null where a rule settles it).

    A rule fits its host and all subdomains if the path starts with the rule's; the longest rule wins. A null URL, or one without "://",
    has an empty host and path and goes to the trees like any other. Without labelled URLs of both kinds there are no trees: the one kind
    there is (or allow) is the verdict. Repeated rows are judged each; an empty table gives an empty result.
    """
    rows = pages.select(F.col(page_id).alias("id"), F.coalesce(F.col(url), F.lit("")).alias("u"))
    parts = split_url(F.col("u"))
    rows = rows.withColumn("host", parts.host).withColumn("path", parts.path)
    rows = rows.withColumn("settled", rule_column(F.col("host"), F.col("path"), rules))
    trees, suffixes, only = fit(rows)
    if trees is None:
        rows = rows.withColumn("p", F.lit(1.0 if only == "block" else 0.0))
    else:
        ready = VectorAssembler(inputCols=list(FEATURES), outputCol="x").transform(_features(rows, suffixes))
        rows = trees.transform(ready).withColumn("p", vector_to_array("probability")[1])
    guess = F.when(F.col("p") >= threshold, "block").otherwise("allow")
    return rows.select(
        F.col("id").alias(page_id),
        "host",
        "path",
        F.col("settled.rule").alias("rule"),
        F.coalesce("settled.verdict", guess).alias("verdict"),
        F.when(F.col("settled").isNull(), F.col("p")).alias("p_block"),
    )


def op7(pages: DataFrame) -> DataFrame:
    return judge(pages)
