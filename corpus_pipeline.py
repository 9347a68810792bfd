"""The corpus pipeline: toxic texts out, repeated lines out, near copies out, benchmark leaks out, then tokens.

Every stage takes all rows that the stage before kept and returns the columns of ``documents``; the last
one returns token ids. Between stages the rows are written as Parquet and read again, so
a stage that fails starts from written rows.

Edge cases: rows with null or empty texts are scored, compared and encoded like others (of all
documents without words one stays); rows that repeat an id are rows of their own; a document that
loses all its lines to earlier ones leaves with them; ``n_chars``, where it is there, follows the
text; further columns pass through; empty tables give empty results. No column of the input may
begin with two underscores (``run`` and the stages refuse it).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm import bpe, decontaminate, line_dedup, near_copies, toxicity
from driftks.llm.tables import remove, settled, shared_folder, table

#: Shingles of five words; fingerprints of texts that differ in so many bits of 64 make candidates, beside MinHash entries.
SHINGLE, BITS = 5, 2
#: Words that an encoding worker remembers: executors hold what the stages before left, and there is time to spare.
WORDS = 60_000


def _checked(docs: DataFrame) -> DataFrame:
    if taken := [c for c in docs.columns if c.startswith("__")]:
        raise ValueError(f"columns named {', '.join(taken)} would be overwritten: rename them first")
    return docs


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose worst window scores below the threshold."""
    labels = table(spark, sf_dir, "labels").where(~toxicity.held_out())
    net = toxicity.fit(docs, labels)
    scored = _checked(docs).withColumn("__toxic", toxicity.scorer(spark, net)(F.coalesce("text", F.lit(""))))
    return scored.where(F.col("__toxic") < toxicity.THRESHOLD).select(*docs.columns)


def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents cut to lines that no earlier one repeats; those that had text and have none left go."""
    named = _checked(docs).withColumn("__had", F.trim(F.coalesce("text", F.lit(""))) != "")
    cleaned = line_dedup.clean(named, counts=("__lines", "__kept"))
    left = cleaned.where(~F.col("__had") | (F.trim("text", F.lit(" \t\r\n")) != "")).select(*docs.columns)
    return left.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else left


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one with the smallest id."""
    rows = settled(_checked(docs).withColumn("__row", F.monotonically_increasing_id()))  # numbered once, whatever is run again
    named = rows.select(F.struct("doc_id", "__row").alias("__key"), "text")
    first = near_copies.firsts(named, "__key", shingle=SHINGLE, bits=BITS).select(F.col("__key.__row").alias("__row"))
    return rows.join(first, "__row", "left_semi").select(*docs.columns)


def without_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage that copies a benchmark item."""
    scored = decontaminate.leak_score(_checked(docs), table(spark, sf_dir, "benchmark"), "__leak")
    return scored.where(F.col("__leak") < decontaminate.LEAST).select(*docs.columns)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``doc_id``, ``n_tokens`` and ``ids`` (little-endian unsigned 32-bit integers) of what is left."""
    return bpe.encode(docs, memory=WORDS).select("doc_id", "n_tokens", "ids")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", without_toxic),
    ("line_dedup", without_repeated_lines),
    ("simhash_near_dedup", without_near_copies),
    ("benchmark_decontamination", without_leaks),
    ("bpe_encoding", encoded),
]

#: SQL expresses neither the network nor the encoding.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, written and read again in the session's shared folder."""
    docs, folder, last = table(spark, sf_dir, "documents"), shared_folder(spark, "pipeline"), None
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if last:
            remove(spark, f"{folder}/{last}")
        last = name
    return docs


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {}
