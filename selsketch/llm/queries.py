"""Queries of this subpackage: name -> (spark, sf_dir) -> DataFrame, and DuckDB SQL where it can express them."""

from __future__ import annotations

from .decontaminate import op2_decontamination
from .licenses import op8_license_scan
from .near_dup import op9_near_dup
from .packing import op4_packing
from .quality import OP10_SQL, op10_quality_rules
from .secrets import op7_secret_scan
from .substring import OP3_SQL, op3_substring_dedup
from .token_counts import op5_token_counts
from .toxicity import op6_toxicity
from .warc import OP1_SQL, op1_warc

QUERIES = {
    "op1_warc": op1_warc,
    "op2_decontamination": op2_decontamination,
    "op3_substring_dedup": op3_substring_dedup,
    "op4_packing": op4_packing,
    "op5_token_counts": op5_token_counts,
    "op6_toxicity": op6_toxicity,
    "op7_secret_scan": op7_secret_scan,
    "op8_license_scan": op8_license_scan,
    "op9_near_dup": op9_near_dup,
    "op10_quality_rules": op10_quality_rules,
}

#: The others have no SQL form: their tests hold them against brute force, round trips or held-out accuracy.
ORACLE_SQL: dict[str, str] = {"op1_warc": OP1_SQL, "op3_substring_dedup": OP3_SQL, "op10_quality_rules": OP10_SQL}
