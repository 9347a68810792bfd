"""Reproducible shuffle into shards by a keyed permutation of global row numbers.

Rows get global numbers 0 .. N-1 in an order that depends on their content alone: hash
bucket of (key, size, checksum), then these columns. A balanced Feistel network permutes the
smallest domain of 4**h numbers that holds N; a number that lands beyond N-1 is permuted again
until it lands inside (cycle walking), which makes a permutation of 0 .. N-1. Place p means shard
``p mod shards`` and slot ``p div shards``, so shard sizes differ by one row at most, slots have
no gaps, and both can be computed, and inverted, from the row number alone.

Only (key, size, checksum) and never a text is shuffled. Equal triples are counted before the
shuffle and numbered as a run, and long runs are cut into pieces, so that no key, however
frequent, fills a task. The counts of the hash buckets are broadcast.

Under this law (``rows``) shards differ by one row at most and nothing else decides: rows with
equal texts are a group for no purpose, and are spread like any others.

Edge cases: a null text has size 1 and the checksum of the empty text; a null key is a key like
others; equal rows take different places of one run; an empty table gives an empty result; other
columns are ignored by ``plan_shards``.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftks.llm.tables import settled, table, whole_text

ROUNDS = 6
#: Rows of a hash bucket, about, and rows that one piece of a run becomes at most.
PER_BUCKET, CHUNK = 1_000_000, 1 << 20


def half_bits(n: int) -> int:
    """The least h with 4**h >= n, 1 at least."""
    return max(1, (max(n - 1, 1).bit_length() + 1) // 2)


def _mixed(half: np.ndarray, key: int, bits: int) -> np.ndarray:
    """A round function: multiply and xor-shift of the half with the round's key, cut to ``bits``."""
    with np.errstate(over="ignore"):
        x = (half + np.uint64(key)) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(32)
    return x & np.uint64((1 << bits) - 1)


def _keys(seed: int) -> list[int]:
    return [int(k) for k in np.random.SeedSequence(seed).generate_state(ROUNDS, np.uint64)]


def permuted(rows: np.ndarray, n: int, seed: int) -> np.ndarray:
    """The place of each row number in a permutation of 0 .. n-1 that ``seed`` picks."""
    bits = half_bits(n)
    mask, shift = np.uint64((1 << bits) - 1), np.uint64(bits)
    out = rows.astype(np.uint64)
    todo = np.arange(len(out))
    while len(todo):
        left, right = out[todo] >> shift, out[todo] & mask
        for key in _keys(seed):
            left, right = right, left ^ _mixed(right, key, bits)
        out[todo] = left << shift | right
        todo = todo[out[todo] >= n]
    return out.astype(np.int64)


def original(places: np.ndarray, n: int, seed: int) -> np.ndarray:
    """The row number at each place: the inverse of ``permuted``."""
    bits = half_bits(n)
    mask, shift = np.uint64((1 << bits) - 1), np.uint64(bits)
    out = places.astype(np.uint64)
    todo = np.arange(len(out))
    while len(todo):
        left, right = out[todo] >> shift, out[todo] & mask
        for key in reversed(_keys(seed)):
            left, right = right ^ _mixed(left, key, bits), left
        out[todo] = left << shift | right
        todo = todo[out[todo] >= n]
    return out.astype(np.int64)


def numbered(rows: DataFrame, per_bucket: int = PER_BUCKET, chunk: int = CHUNK) -> tuple[DataFrame, int]:
    """Add ``row``, a global number from 0 without gaps, to rows of small columns, and return their count.

    Equal rows are counted first and numbered as a run; a run longer than ``chunk`` is cut into pieces that are
    dealt over the tasks before they become rows. Buckets grow with the rows (``per_bucket`` of each), so one bucket is never
    more than a task holds; their counts are collected and broadcast (16 bytes for each ``per_bucket`` rows).
    """
    spark, cols = rows.sparkSession, rows.columns
    buckets = max(4096, rows.count() // per_bucket)
    counted = rows.groupBy(*cols).agg(F.count("*").alias("__n")).withColumn("__b", F.pmod(F.xxhash64(*cols), F.lit(buckets)))
    counted = settled(counted)
    sizes = {r[0]: (r[1], r[2]) for r in counted.groupBy("__b").agg(F.sum("__n"), F.max("__n")).collect()}  # ``buckets`` rows at most
    starts, total = [], 0
    for b in range(buckets):
        starts.append((b, total))
        total += sizes.get(b, (0, 0))[0]
    offsets = F.broadcast(spark.createDataFrame(starts, "__b long, __start long"))
    before = F.sum("__n").over(Window.partitionBy("__b").orderBy(*cols).rowsBetween(Window.unboundedPreceding, -1))
    ranked = counted.withColumn("__before", F.coalesce(before, F.lit(0))).join(offsets, "__b")
    ranked = ranked.select(*cols, "__n", (F.col("__start") + F.col("__before")).alias("__first"))
    run = F.explode(F.sequence(F.col("__first"), F.col("__first") + F.col("__n") - 1))
    if max((m for _, m in sizes.values()), default=0) <= chunk:
        return ranked.select(*cols, run.alias("row")), total
    piece = F.explode(F.sequence(F.lit(0).cast("long"), F.ceil(F.col("__n") / chunk).cast("long") - 1)).alias("__piece")
    begin = F.col("__first") + F.col("__piece") * chunk
    pieces = ranked.select(*cols, "__n", "__first", piece).select(*cols, begin.alias("__first"), F.least(F.lit(chunk).cast("long"), F.col("__n") - F.col("__piece") * chunk).alias("__n"))
    return pieces.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "__first").select(*cols, run.alias("row")), total


def plan_shards(df: DataFrame, shards: int = 16, seed: int = 20, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key``, ``size``, ``text_crc32``, ``row``, ``place``, ``shard`` and ``slot`` of every row of ``df``."""
    body = whole_text(text)
    rows, n = numbered(df.select(F.col(key), (F.octet_length(body) + F.lit(1)).cast("long").alias("size"), F.crc32(F.encode(body, "UTF-8")).alias("text_crc32")))

    @F.pandas_udf("long")
    def place(row: pd.Series) -> pd.Series:
        return pd.Series(permuted(row.to_numpy(), n, seed))

    return rows.withColumn("place", place("row")).withColumn("shard", F.pmod("place", F.lit(shards)).cast("int")).withColumn("slot", F.floor(F.col("place") / shards).cast("long"))


def op2_feistel_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 16 shards whose row counts differ by one at most (law ``rows``)."""
    planned = plan_shards(table(spark, sf_dir, "documents"))
    return planned.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "row")
