"""The queries of the corpus operators and their SQL."""

from __future__ import annotations

from vpatterns.llm import bpe, hmm, jaccard, langid, media, mixing, quality, repeats, tokens, toxicity


def queries() -> dict:
    return {
        "op1_fair_queue_mix": mixing.op1_fair_queue_mix,
        "op2_bitmask_langid": langid.op2_bitmask_langid,
        "op3_mcd_outliers": quality.op3_mcd_outliers,
        "op4_iso_media": media.op4_iso_media,
        "op5_fragment_jaccard": jaccard.op5_fragment_jaccard,
        "op6_offset_attribution": tokens.op6_offset_attribution,
        "op7_hidden_markov": hmm.op7_hidden_markov,
        "op8_prefix_free_repeats": repeats.op8_prefix_free_repeats,
        "op9_bpe_tree": bpe.op9_bpe_tree,
        "op10_noisy_channel_toxicity": toxicity.op10_noisy_channel_toxicity,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_fair_queue_mix": mixing.MIX_SQL}
