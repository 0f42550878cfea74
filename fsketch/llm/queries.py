"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from .bpe import op4_byte_bpe
from .decontamination import op6_decontamination
from .quality_classifier import op5_quality_classifier
from .quality_rules import OP1_SQL, op1_quality_rules
from .sharding import OP9_SQL, op9_sharding
from .simhash import op10_simhash
from .substring_dedup import OP7_SQL, op7_substring_dedup
from .token_counts import op2_token_counts
from .url_filters import OP3_SQL, op3_url_filters
from .warc import OP8_SQL, op8_warc

QUERIES = {
    "op1_quality_rules": op1_quality_rules,
    "op2_token_counts": op2_token_counts,
    "op3_url_filters": op3_url_filters,
    "op4_byte_bpe": op4_byte_bpe,
    "op5_quality_classifier": op5_quality_classifier,
    "op6_decontamination": op6_decontamination,
    "op7_substring_dedup": op7_substring_dedup,
    "op8_warc": op8_warc,
    "op9_sharding": op9_sharding,
    "op10_simhash": op10_simhash,
}

#: The others are not expressible in SQL and are tested against brute force or exact round trips.
ORACLE_SQL = {"op1_quality_rules": OP1_SQL, "op3_url_filters": OP3_SQL, "op7_substring_dedup": OP7_SQL, "op8_warc": OP8_SQL, "op9_sharding": OP9_SQL}
