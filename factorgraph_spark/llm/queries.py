"""The queries of this subpackage, by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from . import ann, langid, license_scan, mixture, neardup, packing, quality, secret_scan, url_filter, warc
from .common import table


def queries() -> dict:
    docs = lambda f: lambda spark, sf_dir: f(table(spark, sf_dir, "documents"))
    pages = lambda f: lambda spark, sf_dir: f(table(spark, sf_dir, "pages"))
    return {
        "op1_license_scan": docs(license_scan.op1),
        "op2_source_mixture": docs(mixture.op2),
        "op3_language_id": docs(langid.op3),
        "op4_permutation_index": lambda spark, sf_dir: ann.op4(table(spark, sf_dir, "embeddings")),
        "op5_quality_rules": lambda spark, sf_dir: quality.op5(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")),
        "op6_secret_scan": docs(secret_scan.op6),
        "op7_url_filter": pages(url_filter.op7),
        "op8_warc_revisits": pages(warc.op8),
        "op9_near_duplicates": docs(neardup.op9),
        "op10_best_fit_packing": docs(packing.pack),
    }


def oracle_sql() -> dict[str, str]:
    return {}
