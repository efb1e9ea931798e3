"""Queries of this subpackage, one per operator, and their SQL."""

from __future__ import annotations

from . import bpe, decontaminate, embdup, html, langid, neardup, sharding, substrings, urlfilter, warc
from .common import table

QUERIES = {
    "op1_sharding": lambda s, d: sharding.compact_documents(table(s, d, "documents")),
    "op2_decontamination": lambda s, d: decontaminate.annotate(table(s, d, "documents"), table(s, d, "benchmark")),
    "op3_language_id": lambda s, d: langid.identify(table(s, d, "documents")),
    "op4_url_filters": lambda s, d: urlfilter.judge(table(s, d, "pages")),
    "op5_substring_dedup": lambda s, d: substrings.digests(table(s, d, "documents")),
    "op6_html_extraction": lambda s, d: html.extract(table(s, d, "pages")),
    "op7_minhash_near_dedup": lambda s, d: neardup.components(table(s, d, "documents"), shingle=3, percent=85),
    "op8_bpe": lambda s, d: bpe.round_trip(table(s, d, "documents")),
    "op9_warc": lambda s, d: warc.archive(table(s, d, "pages")),
    "op10_embedding_near_dedup": lambda s, d: embdup.near_duplicates(table(s, d, "embeddings")),
}

ORACLES = {
    "op1_sharding": sharding.ORACLE,
    "op2_decontamination": decontaminate.ORACLE,
    "op4_url_filters": urlfilter.ORACLE,
    "op5_substring_dedup": substrings.ORACLE,
    "op7_minhash_near_dedup": neardup.ORACLE,
    "op9_warc": warc.ORACLE,
    "op10_embedding_near_dedup": embdup.ORACLE,
}
