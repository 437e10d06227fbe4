"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from .bpe import op1_byte_bpe
from .decontam import OP6_SQL, op6_decontamination
from .htmltext import op7_html_text
from .pii import op5_personal_data
from .quality import op8_quality_classifier
from .rules import OP9_SQL, op9_quality_rules
from .sharding import OP10_SQL, op10_sharding
from .simhash import op2_simhash_near_dedup
from .substring import OP3_SQL, op3_substring_dedup
from .urlfilter import OP4_SQL, op4_url_filter


def queries() -> dict:
    ops = (op1_byte_bpe, op2_simhash_near_dedup, op3_substring_dedup, op4_url_filter, op5_personal_data, op6_decontamination, op7_html_text, op8_quality_classifier, op9_quality_rules, op10_sharding)
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    return {"op3_substring_dedup": OP3_SQL, "op4_url_filter": OP4_SQL, "op6_decontamination": OP6_SQL, "op9_quality_rules": OP9_SQL, "op10_sharding": OP10_SQL}
