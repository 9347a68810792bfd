"""Connected components of an edge table, by alternating star contraction.

Each round links the neighbours of every node to the least node known there: first those larger
than the node (large star), then the node and those smaller (small star). Both keep the
components, and every component ends as a star around its least node. A round shuffles the
edges once for each star, with ``min`` and nothing else pre-aggregated; a hub's edges are not
gathered in a row anywhere. Rounds are cut by checkpoints in the shared folder, so a lost
executor costs at most one round. Edges that need fewer tasks than the session's shuffle partitions
are worked on by as many as ``PER_TASK`` edges each call for: a round writes files for every task, and
most rounds are over few edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftks.llm.tables import settled

PER_TASK = 20_000


def _dealt(df: DataFrame, edges: int) -> DataFrame:
    """``df`` in the tasks that so many edges need, where these are fewer than the shuffle partitions."""
    tasks = edges // PER_TASK + 1
    return df.coalesce(tasks) if tasks < int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) else df


def _star(edges: DataFrame, large: bool, n: int) -> DataFrame:
    """``edges``: (u, v) with u > v, some ``n`` of them. One contraction; returns such edges again."""
    if large:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = _dealt(both.groupBy("u").agg(F.min("v").alias("m")), n).withColumn("m", F.least("u", "m"))
        out = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        return _dealt(_dealt(out.where("u <> v"), n).distinct(), n)
    least = _dealt(edges.groupBy("u").agg(F.min("v").alias("m")), n)
    moved = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return _dealt(_dealt(moved.union(least.select("u", F.col("m").alias("v"))), n).distinct(), n)


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """``node`` and ``root`` (the least node of its component) for every node that ``edges`` (a, b) name.

    Self loops and null ends are ignored; edges may repeat and point either way.
    """
    e = settled(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    before, n = None, e.count()
    for _ in range(rounds):
        e = _dealt(e, n)
        e = settled(_star(_star(e, True, n), False, n))
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before, n = now, now[0]
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).union(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
