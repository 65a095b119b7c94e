"""The subpackage's queries and their SQL, by name."""

from __future__ import annotations

from cellscrub.llm import chat_events, deobfuscation, hidden_markov, jaccard_join, merge_dropout, pii_votes, quality_hosts, relative_dedup, sharding, winnowing

QUERIES = {
    "op1_merge_dropout": merge_dropout.merge_dropout_query,
    "op2_chat_events": chat_events.chat_query,
    "op3_quality_hosts": quality_hosts.quality_query,
    "op4_pii_votes": pii_votes.pii_query,
    "op5_sharding": sharding.sharding_query,
    "op6_relative_dedup": relative_dedup.dedup_query,
    "op7_hidden_markov": hidden_markov.language_model_query,
    "op8_winnowing": winnowing.decontamination_query,
    "op9_deobfuscation": deobfuscation.toxicity_query,
    "op10_jaccard_join": jaccard_join.jaccard_query,
}
SQL = {
    "op2_chat_events": chat_events.CHAT_SQL,
    "op3_quality_hosts": quality_hosts.QUALITY_SQL,
    "op5_sharding": sharding.SHARDING_SQL,
    "op6_relative_dedup": relative_dedup.DEDUP_SQL,
    "op8_winnowing": winnowing.DECONTAMINATION_SQL,
    "op10_jaccard_join": jaccard_join.JACCARD_SQL,
}
