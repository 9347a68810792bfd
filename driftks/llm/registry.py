"""The queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from driftks.llm import bpe, decontaminate, language_id, line_dedup, neighbors, secret_scan, sharding, simhash, toxicity, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [
        secret_scan.op1_secret_scan,
        sharding.op2_feistel_shards,
        decontaminate.op3_decontamination,
        language_id.op4_language_id,
        warc.op5_warc_revisits,
        toxicity.op6_toxicity,
        simhash.op7_simhash_components,
        line_dedup.op8_line_dedup,
        bpe.op9_bpe_round_trip,
        neighbors.op10_nearest_neighbours,
    ]
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op5_warc_revisits": warc.OP5_SQL, "op8_line_dedup": line_dedup.OP8_SQL}
