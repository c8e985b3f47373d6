"""Queries of this subpackage and their SQL twins, by name."""

from __future__ import annotations

from . import decontaminate, exact_dedup, jaccard_join, language_id, packing, repeated_passages, secret_scan, sharding, toxicity, url_rules

QUERIES = {
    "op1_decontaminate": decontaminate.query,
    "op2_secret_scan": secret_scan.query,
    "op3_hypergeometric_shards": sharding.query,
    "op4_toxicity": toxicity.query,
    "op5_exact_dedup": exact_dedup.query,
    "op6_repeated_passages": repeated_passages.query,
    "op7_jaccard_join": jaccard_join.query,
    "op8_language_id": language_id.query,
    "op9_url_rules": url_rules.query,
    "op10_packing": packing.query,
}
SQL = {
    "op1_decontaminate": decontaminate.SQL,
    "op6_repeated_passages": repeated_passages.SQL,
    "op5_exact_dedup": exact_dedup.SQL,
    "op7_jaccard_join": jaccard_join.SQL,
}
