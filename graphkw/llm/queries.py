"""The registered queries of this folder and the SQL of those that SQL can express."""

from __future__ import annotations

from .decision_list import op7_quality_rules
from .decontaminate import OP4_SQL, op4_decontamination
from .html_text import op10_html_text
from .line_dedup import op8_line_dedup
from .minhash import OP3_SQL, op3_minhash_dedup
from .packing import op2_packing
from .quality_knn import op1_quality_classifier
from .suffix_dedup import OP5_SQL, op5_suffix_dedup
from .token_counts import op9_token_counts
from .url_filter import OP6_SQL, op6_url_filter

QUERIES = {
    "op1_quality_classifier": op1_quality_classifier,
    "op2_packing": op2_packing,
    "op3_minhash_dedup": op3_minhash_dedup,
    "op4_decontamination": op4_decontamination,
    "op5_suffix_dedup": op5_suffix_dedup,
    "op6_url_filter": op6_url_filter,
    "op7_quality_rules": op7_quality_rules,
    "op8_line_dedup": op8_line_dedup,
    "op9_token_counts": op9_token_counts,
    "op10_html_text": op10_html_text,
}
ORACLE_SQL = {"op3_minhash_dedup": OP3_SQL, "op4_decontamination": OP4_SQL, "op5_suffix_dedup": OP5_SQL, "op6_url_filter": OP6_SQL}
