"""Queries and SQL of the training-data operators, for __spark_entry__.py."""

from __future__ import annotations

from . import decontaminate, embed_dedup, langid, license_scan, packing, pii, quality_mil, simhash, sstable, url_filter

QUERIES = {
    "op1_sstable_shards": sstable.op1,
    "op2_embedding_neardup": embed_dedup.op2,
    "op3_license_scan": license_scan.op3,
    "op4_best_fit_packing": packing.op4,
    "op5_quality_mil": quality_mil.op5,
    "op6_language_id": langid.op6,
    "op7_simhash": simhash.op7,
    "op8_url_filter": url_filter.op8,
    "op9_pii": pii.op9,
    "op10_decontaminate": decontaminate.op10,
}

ORACLES = {
    "op8_url_filter": url_filter.ORACLE,
}
