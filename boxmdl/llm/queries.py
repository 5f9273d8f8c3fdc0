"""The corpus operators' queries and SQL oracles."""

from __future__ import annotations

from . import fingerprint, html_text, langid, line_rules, mixing, neardup, oracles, packing, sharding, suffix_dedup, toxicity

QUERIES = {
    "op1_cost_balanced_packing": packing.op1_cost_balanced_packing,
    "op2_coordinate_join_neardup": neardup.op2_coordinate_join_neardup,
    "op3_site_template_removal": html_text.op3_site_template_removal,
    "op4_prefix_sum_shards": sharding.op4_prefix_sum_shards,
    "op5_weighted_fair_mix": mixing.op5_weighted_fair_mix,
    "op6_line_frequency_rules": line_rules.op6_line_frequency_rules,
    "op7_induced_suffix_dedup": suffix_dedup.op7_induced_suffix_dedup,
    "op8_clause_grammar_toxicity": toxicity.op8_clause_grammar_toxicity,
    "op9_kneser_ney_languages": langid.op9_kneser_ney_languages,
    "op10_canonical_digest": fingerprint.op10_canonical_digest,
}

ORACLES = {
    "op2_coordinate_join_neardup": oracles.OP2_SQL,
    "op4_prefix_sum_shards": oracles.OP4_SQL,
    "op5_weighted_fair_mix": mixing.OP5_SQL,
    "op6_line_frequency_rules": line_rules.OP6_SQL,
    "op7_induced_suffix_dedup": oracles.OP7_SQL,
}
