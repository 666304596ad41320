"""Queries and SQL of the operators for training-data pipelines."""

from __future__ import annotations

import corpus_pipeline
from aggclust.llm import bpe_codec, embeddings, fingerprints, mixing, near_duplicates, pii, quality, secrets, sharding, token_counts


def queries() -> dict:
    return {
        "op1_fingerprints": fingerprints.op1_fingerprints,
        "op2_embeddings": embeddings.op2_embeddings,
        "op3_pii": pii.op3_pii,
        "op4_near_duplicates": near_duplicates.op4_near_duplicates,
        "op5_secrets": secrets.op5_secrets,
        "op6_sharding": sharding.op6_sharding,
        "op7_token_counts": token_counts.op7_token_counts,
        "op8_bpe_codec": bpe_codec.op8_bpe_codec,
        "op9_mixing": mixing.op9_mixing,
        "op10_quality": quality.op10_quality,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    found = {"op2_embeddings": embeddings.oracle(), "op9_mixing": mixing.oracle()}
    if corpus_pipeline.ORACLE_SQL:
        found["pipeline"] = corpus_pipeline.ORACLE_SQL
    return found
