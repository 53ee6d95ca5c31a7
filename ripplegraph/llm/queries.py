"""The registered queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from ripplegraph.llm import op1_license_scan as op1
from ripplegraph.llm import op2_warc as op2
from ripplegraph.llm import op3_substring_dedup as op3
from ripplegraph.llm import op4_url_filter as op4
from ripplegraph.llm import op5_ngram_join as op5
from ripplegraph.llm import op6_decontamination as op6
from ripplegraph.llm import op7_toxicity as op7
from ripplegraph.llm import op8_pii as op8
from ripplegraph.llm import op9_quality as op9
from ripplegraph.llm import op10_mixing as op10

QUERIES = {
    "op1_license_scan": op1.op1_license_scan,
    "op2_warc": op2.op2_warc,
    "op3_substring_dedup": op3.op3_substring_dedup,
    "op4_url_filter": op4.op4_url_filter,
    "op5_ngram_join": op5.op5_ngram_join,
    "op6_decontamination": op6.op6_decontamination,
    "op7_toxicity": op7.op7_toxicity,
    "op8_pii": op8.op8_pii,
    "op9_quality": op9.op9_quality,
    "op10_mixing": op10.op10_mixing,
    "quality_base_counts": op9.quality_base_counts,
}
ORACLES = {
    "op2_warc": op2.ORACLE,
    "op3_substring_dedup": op3.ORACLE,
    "op4_url_filter": op4.ORACLE,
    "op5_ngram_join": op5.ORACLE,
    "op6_decontamination": op6.ORACLE,
    "op10_mixing": op10.ORACLE,
    "quality_base_counts": op9.BASE_ORACLE,
}
