"""Queries of this package by name, and the SQL twins of those that SQL can express."""

from __future__ import annotations

from . import mixing, packing, placement, progressive, quality, repeats, repetition, secrets, simhash, tokens


def queries():
    return {
        "op1_secret_scan": secrets.op1,
        "op2_repetition_rules": repetition.op2,
        "op3_repeated_substrings": repeats.op3,
        "op4_quality_classifier": quality.op4,
        "op5_sharding": placement.op5,
        "op6_token_counts": tokens.op6,
        "op7_progressive_media": progressive.op7,
        "op8_source_mix": mixing.op8,
        "op9_simhash_near_dedup": simhash.op9,
        "op10_sequence_packing": packing.op10,
    }


def oracle_sql():
    return {"op5_sharding": placement.op5_sql(), "op8_source_mix": mixing.OP8_SQL}
