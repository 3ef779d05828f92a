"""Queries and DuckDB statements of the training-data operators."""

from __future__ import annotations

from evenpart.llm.document_fingerprints import op8_order_minhash
from evenpart.llm.exact_dedup import OP2_SQL, op2_exact_dedup
from evenpart.llm.license_scan import op5_license_scan
from evenpart.llm.mixing import op4_source_mix
from evenpart.llm.packing import op9_pack
from evenpart.llm.pii_surrogates import op6_pii_surrogates
from evenpart.llm.simhash import op3_simhash
from evenpart.llm.suffix_dedup import op7_suffix_dedup
from evenpart.llm.toxicity import op10_toxicity
from evenpart.llm.url_filters import OP1_SQL, op1_url_filter

QUERIES = {
    "op1_url_filter": op1_url_filter,
    "op2_exact_dedup": op2_exact_dedup,
    "op3_simhash": op3_simhash,
    "op4_source_mix": op4_source_mix,
    "op5_license_scan": op5_license_scan,
    "op6_pii_surrogates": op6_pii_surrogates,
    "op7_suffix_dedup": op7_suffix_dedup,
    "op8_order_minhash": op8_order_minhash,
    "op9_pack": op9_pack,
    "op10_toxicity": op10_toxicity,
}
ORACLES = {"op1_url_filter": OP1_SQL, "op2_exact_dedup": OP2_SQL}
