"""The queries of this subpackage, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontaminate, license_scan, media, pii, piece_codec, secrets_scan, simhash, substring, toxicity, url_filter
from .common import read_table


def _on(operator: Callable[..., DataFrame], *tables: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: operator(*(read_table(spark, sf_dir, t) for t in tables))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_license_scan": _on(license_scan.op1, "documents"),
    "op2_simhash": _on(simhash.op2, "documents"),
    "op3_secret_scan": _on(secrets_scan.op3, "documents"),
    "op4_substring_dedup": _on(substring.op4, "documents"),
    "op5_piece_codec": _on(piece_codec.op5, "documents"),
    "op6_toxicity": _on(toxicity.op6, "documents", "labels"),
    "op7_url_filter": _on(url_filter.op7, "pages"),
    "op8_decontaminate": _on(decontaminate.op8, "documents", "benchmark"),
    "op9_pii": _on(pii.op9, "documents"),
    "op10_media": _on(media.op10, "documents"),
}

ORACLES: dict[str, str] = {
    "op1_license_scan": license_scan.sql(),
    "op3_secret_scan": secrets_scan.sql(),
    "op7_url_filter": url_filter.SQL,
    "op8_decontaminate": decontaminate.SQL,
}
