"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from subwin.llm.bpe import op3_byte_bpe
from subwin.llm.exact_dedup import OP7_SQL, op7_exact_dedup
from subwin.llm.license_scan import OP8_SQL, op8_license_scan
from subwin.llm.lm_scoring import op4_lm_scoring
from subwin.llm.quality_rules import OP2_SQL, op2_quality_rules
from subwin.llm.secret_scan import op9_secret_scan
from subwin.llm.simhash_dedup import op10_simhash_dedup
from subwin.llm.source_mixing import op5_source_mixing
from subwin.llm.substring_dedup import OP6_SQL, op6_substring_dedup
from subwin.llm.url_filters import OP1_SQL, op1_url_filters

QUERIES = {
    f.__name__: f
    for f in (op1_url_filters, op2_quality_rules, op3_byte_bpe, op4_lm_scoring, op5_source_mixing, op6_substring_dedup, op7_exact_dedup, op8_license_scan, op9_secret_scan, op10_simhash_dedup)
}
#: The others are not to be had in SQL: BPE, hash-driven chance and models, XXH64.
SQL = {"op1_url_filters": OP1_SQL, "op2_quality_rules": OP2_SQL, "op6_substring_dedup": OP6_SQL, "op7_exact_dedup": OP7_SQL, "op8_license_scan": OP8_SQL}
