"""The operators' queries, and SQL for those that SQL can express."""

from __future__ import annotations

from . import bpe, lm, mixing, neighbours, pii, quality, simhash, suffixes, toxicity, urls


def queries() -> dict:
    import corpus_pipeline

    ops = (
        bpe.op1_bpe_roundtrip, simhash.op2_simhash_groups, pii.op3_surrogates, mixing.op4_source_mix, quality.op5_quality_rules,
        urls.op6_url_filter, suffixes.op7_repeated_spans, lm.op8_lm_score, toxicity.op9_toxicity, neighbours.op10_nearest,
    )
    return {f.__name__: f for f in ops} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op4_source_mix": mixing.OP4_SQL, "op6_url_filter": urls.OP6_SQL}
