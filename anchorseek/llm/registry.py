"""Queries of this subpackage and the DuckDB SQL that checks them."""

from __future__ import annotations

from . import langid, licenses, lsh_forest, mixing, quality, secrets, token_files, toxicity, url_rules, winnow


def queries():
    return {
        "op1_url_filter": url_rules.op1_url_filter,
        "op2_quality": quality.op2_quality,
        "op3_near_duplicates": lsh_forest.op3_near_duplicates,
        "op4_tokens": token_files.op4_tokens,
        "op5_decontaminate": winnow.op5_decontaminate,
        "op6_toxicity": toxicity.op6_toxicity,
        "op7_licenses": licenses.op7_licenses,
        "op8_secrets": secrets.op8_secrets,
        "op9_mix": mixing.op9_mix,
        "op10_language": langid.op10_language,
    }


def oracle_sql():
    return {"op1_url_filter": url_rules.OP1_SQL, "op3_near_duplicates": lsh_forest.OP3_SQL, "op5_decontaminate": winnow.OP5_SQL, "op9_mix": mixing.OP9_SQL}
