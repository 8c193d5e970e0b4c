"""Queries of the training-data operators, with their SQL."""

from __future__ import annotations

from graphsplit.llm import cleaning, impact_index, language, link_trust, mixing, near_dup, packing, privacy, rules, toxicity
from graphsplit.llm.common import table


def op1_pareto_mix(spark, sf_dir):
    return mixing.plan(table(spark, sf_dir, "documents"))


def op2_pattern_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"))


def op5_line_cleaning(spark, sf_dir):
    return cleaning.clean(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text", "cleaned")


def op4_rule_ensemble(spark, sf_dir):
    return rules.scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_output_codes(spark, sf_dir):
    return language.predictions(table(spark, sf_dir, "documents"))


def op10_noisy_or(spark, sf_dir):
    return toxicity.scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_link_trust(spark, sf_dir):
    return link_trust.judge(table(spark, sf_dir, "pages"))


def op8_impact_index(spark, sf_dir):
    return impact_index.nearest(table(spark, sf_dir, "embeddings")).drop("segments", "rescored")


def op7_weak_supervision(spark, sf_dir):
    return privacy.find(table(spark, sf_dir, "documents"))


def op9_super_minhash(spark, sf_dir):
    return near_dup.group(table(spark, sf_dir, "documents"), width=3, limit=0.85)


QUERIES = {
    "op9_super_minhash": op9_super_minhash,
    "op7_weak_supervision": op7_weak_supervision,
    "op3_link_trust": op3_link_trust,
    "op8_impact_index": op8_impact_index,
    "op4_rule_ensemble": op4_rule_ensemble,
    "op6_output_codes": op6_output_codes,
    "op10_noisy_or": op10_noisy_or,
    "op5_line_cleaning": op5_line_cleaning,
    "op2_pattern_packing": op2_pattern_packing,
    "op1_pareto_mix": op1_pareto_mix,
}

SQL = {
    "op9_super_minhash": near_dup.SQL,
    "op8_impact_index": impact_index.SQL,
    "op5_line_cleaning": cleaning.SQL,
    "op1_pareto_mix": mixing.SQL,
}
