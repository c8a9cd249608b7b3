"""Queries of the operators, and SQL where SQL can express them."""

from . import contamination, jaccard, licenses, mixing, pii, quality, records, sharding, substrings, warc

QUERIES = {
    "op1_induced_suffix_sorting": substrings.op1_induced_suffix_sorting,
    "op2_binary_records": records.op2_binary_records,
    "op3_anchor_expansion": pii.op3_anchor_expansion,
    "op4_quality_rules": quality.op4_quality_rules,
    "op5_warc_normaliser": warc.op5_warc_normaliser,
    "op6_minhash_containment": contamination.op6_minhash_containment,
    "op8_rare_token_index": licenses.op8_rare_token_index,
    "op7_karmarkar_karp": sharding.op7_karmarkar_karp,
    "op10_adaptive_prefixes": jaccard.op10_adaptive_prefixes,
    "op9_low_discrepancy_mix": mixing.op9_low_discrepancy_mix,
}
ORACLES: dict[str, str] = {"op5_warc_normaliser": warc.ORACLE}
