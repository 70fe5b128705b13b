"""Queries of the corpus operators, and the DuckDB SQL of those that SQL can express."""

from __future__ import annotations

from .decontamination import op3_decontamination
from .html_text import op2_html_text
from .language_id import op8_language_id
from .mixing import op7_mixing
from .near_duplicates import OP6_SQL, op6_near_duplicates
from .quality_rules import OP4_SQL, op4_quality_rules
from .secret_scan import OP1_SQL, op1_secret_scan
from .substring_dedup import OP9_SQL, op9_substring_dedup
from .token_counts import op10_token_counts
from .url_filter import OP5_SQL, op5_url_filter

QUERIES = {
    "op1_secret_scan": op1_secret_scan,
    "op2_html_text": op2_html_text,
    "op3_decontamination": op3_decontamination,
    "op4_quality_rules": op4_quality_rules,
    "op5_url_filter": op5_url_filter,
    "op6_near_duplicates": op6_near_duplicates,
    "op7_mixing": op7_mixing,
    "op8_language_id": op8_language_id,
    "op9_substring_dedup": op9_substring_dedup,
    "op10_token_counts": op10_token_counts,
}

ORACLES: dict[str, str] = {
    "op1_secret_scan": OP1_SQL,
    "op4_quality_rules": OP4_SQL,
    "op5_url_filter": OP5_SQL,
    "op6_near_duplicates": OP6_SQL,
    "op9_substring_dedup": OP9_SQL,
}
