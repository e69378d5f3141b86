"""Queries of this package and their SQL, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from outline_engine.llm import bpe, chat, classifier, fingerprints, katz, packing, quality_rules, rollups, simhash, warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_chat": chat.op1_chat,
    "op2_simhash": simhash.op2_simhash,
    "op3_bpe": bpe.op3_bpe,
    "op4_katz": katz.op4_katz,
    "op5_quality_rules": quality_rules.op5_quality_rules,
    "op6_token_rollup": rollups.op6_token_rollup,
    "op7_classifier": classifier.op7_classifier,
    "op8_warc": warc.op8_warc,
    "op9_packing": packing.op9_packing,
    "op10_syncmers": fingerprints.op10_syncmers,
}
ORACLES: dict[str, str] = {
    "op1_chat": chat.OP1_SQL,
    "op5_quality_rules": quality_rules.OP5_SQL,
    "op8_warc": warc.OP8_SQL,
}
