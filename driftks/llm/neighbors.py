"""Approximate nearest neighbours by inner product, from a forest of random-projection trees.

The trees are fitted on a bounded sample of vectors (``fit_values`` numbers). A level of a tree has one
direction, orthogonal to those of its other levels; a node of the level is cut at the sample's
median along it, down to leaves of about ``leaf`` vectors (or of four sample vectors). Every
vector of the table is put into one leaf of each tree. A leaf is worth what the means of its path promise:
the sum, over the levels, of the query's and the path's coordinate. All leaves of all trees wait
in one priority queue by that worth; a query takes the first ``visits`` of them (the queue is
emptied by selection, not leaf by leaf), and the candidates there are ranked by exact inner
products in double precision.

How many leaves ``recall`` takes is measured on the sample: queries of it, with all their nearest
sample vectors, tell how deep in the queue these lie. Structured data need few leaves. In data
without structure (independent normal components) near vectors hide in many; the number then
grows with the table, and ``visits`` can be given as a budget instead.

Work is joined by parts, runs of neighbouring leaves with ``block`` vectors or so: a query and its vector
go once to each part in which it visits leaves, with these as a bitmap. A leaf larger than a block
is dealt out over several groups by a hash of the id and its queries go to all of them; a part that
more than ``query_block`` queries ask is repeated for each such portion of them (counted first), so no group
grows with the data. The k-th best of the sample vectors that a query visits is a lower bound,
below which parts report nothing. A query that finds fewer than ``k`` rows is searched again
through all leaves.

Equal vectors score alike, so of the rows with one vector the ``k`` + 1 smallest ids are all that
can be among the ``k`` nearest (one of them may be the query's own); the others leave at the start.

Edge cases: vectors that are null, empty, zero, or hold null or non-finite components take no part;
null ids neither; vectors of different lengths meet with the shorter one filled up by zeros;
rows that repeat id and vector are one; rows that repeat an id are one candidate (their best
score), and one query (its least vector); ties go to the smaller id; with fewer candidates than
``k`` all are returned; an empty table or no query gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftks.llm.tables import settled, table
from driftks.plans.shipping import held, share

TREES, LEAF = 4, 16
#: Share of the nearest sample vectors that the visited leaves must hold.
RECALL = 0.96
#: Numbers (rows times length) that the fit sample holds, and the sample queries that measure recall.
FIT_VALUES, MEASURED = 1 << 21, 200
#: Rows that a query's leaves hold at least (in all trees), in multiples of ``k``.
AT_LEAST = 16
BLOCK, QUERY_BLOCK = 16_384, 32_768


class Forest:
    """Directions, cuts and side means of all trees; leaves are numbered through all of them."""

    def __init__(self, sample: np.ndarray, rows: int, trees: int = TREES, leaf: int = LEAF, seed: int = 10):
        r = np.random.default_rng(seed)
        dim = sample.shape[1]
        self.depth = max(0, int(np.floor(np.log2(max(1.0, min(rows / leaf, len(sample) / 4))))))
        self.trees = trees if self.depth else 1
        self.per_tree = 1 << self.depth
        self.leaves = self.trees * self.per_tree
        turns = -(-max(self.depth, 1) // dim)
        self.ways = [np.hstack([np.linalg.qr(r.normal(size=(dim, dim)))[0] for _ in range(turns)])[:, : self.depth] for _ in range(self.trees)]
        self.cuts: list[list[np.ndarray]] = []
        self.means: list[list[np.ndarray]] = []  # of a level: the means of both sides of each node
        for way in self.ways:
            side, at = sample @ way, np.zeros(len(sample), np.int64)
            cuts, means = [], []
            for level in range(self.depth):
                s, nodes = side[:, level], 1 << level
                order = np.lexsort((s, at))
                first = np.searchsorted(at[order], np.arange(nodes + 1))
                size = np.diff(first)
                middle = s[order][np.minimum(first[:-1] + size // 2, len(s) - 1)]
                cut = np.where(size > 0, middle, 0.0)
                at = 2 * at + (s >= cut[at])
                count, total = np.bincount(at, minlength=2 * nodes), np.bincount(at, s, 2 * nodes)
                cuts.append(cut)
                means.append(np.where(count > 0, total / np.maximum(count, 1), np.repeat(cut, 2)))
            self.cuts.append(cuts)
            self.means.append(means)

    def place(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each vector in each tree."""
        out = np.empty((len(x), self.trees), np.int32)
        for t, way in enumerate(self.ways):
            side, at = x @ way, np.zeros(len(x), np.int64)
            for level, cut in enumerate(self.cuts[t]):
                at = 2 * at + (side[:, level] >= cut[at])
            out[:, t] = t * self.per_tree + at
        return out

    def worth(self, q: np.ndarray) -> np.ndarray:
        """What every leaf promises each query: the priorities of the shared queue."""
        out = np.empty((len(q), self.leaves))
        for t, way in enumerate(self.ways):
            side, sums = q @ way, np.zeros((len(q), 1))
            for level, mean in enumerate(self.means[t]):
                sums = np.repeat(sums, 2, axis=1) + side[:, level, None] * mean
            out[:, t * self.per_tree : (t + 1) * self.per_tree] = sums
        return out

    def visited(self, q: np.ndarray, visits: int) -> np.ndarray:
        """Which leaves each query takes from the queue."""
        if visits >= self.leaves:
            return np.ones((len(q), self.leaves), bool)
        first = np.argpartition(-self.worth(q), visits, axis=1)[:, :visits]
        out = np.zeros((len(q), self.leaves), bool)
        np.put_along_axis(out, first, True, axis=1)
        return out

    def needed(self, sample: np.ndarray, ids: np.ndarray, k: int, recall: float, measured: int = MEASURED) -> int:
        """How many leaves of the queue hold the share ``recall`` of the ``k`` nearest sample vectors of sample queries."""
        if self.leaves == 1 or len(sample) < 2:
            return self.leaves
        leaves, depths = self.place(sample), []
        some = np.linspace(0, len(sample) - 1, min(measured, len(sample))).astype(int)
        for at in range(0, len(some), 32):
            mine = some[at : at + 32]
            score = sample[mine] @ sample.T
            score[ids[mine][:, None] == ids] = -np.inf
            best = np.argsort(-score, axis=1, kind="stable")[:, :k]
            rank = np.argsort(np.argsort(-self.worth(sample[mine]), axis=1), axis=1)
            depths.append(np.stack([rank[i, leaves[b]].min(1) for i, b in enumerate(best)]).ravel())
        return int(np.quantile(np.concatenate(depths), recall, method="higher")) + 1


def matrix(rows, dim: int) -> np.ndarray:
    """An Arrow array of lists as rows of ``dim`` doubles, shorter ones filled up by zeros."""
    rows = rows.combine_chunks() if isinstance(rows, pa.ChunkedArray) else rows
    if isinstance(rows, pa.ChunkedArray):
        rows = pa.concat_arrays(rows.chunks) if rows.num_chunks else pa.array([], pa.list_(pa.float64()))
    flat = rows.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    lens = np.diff(rows.offsets.to_numpy())
    if (lens == dim).all():
        return flat.reshape(len(rows), dim)
    out = np.zeros((len(rows), dim))
    owner = np.repeat(np.arange(len(rows)), lens)
    out[owner, np.arange(len(flat)) - np.repeat(np.cumsum(lens) - lens, lens)] = flat
    return out


def inner(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of paired rows, added up from the first component to the last."""
    out = np.zeros(len(a))
    for d in range(a.shape[1]):
        out += a[:, d] * b[:, d]
    return out


def best_ids(score: np.ndarray, ids: np.ndarray, k: int, floor: float) -> np.ndarray:
    """Places of all rows of the ``k`` best distinct ``ids`` (and of rows that tie with them) that reach ``floor``."""
    at = np.flatnonzero(score >= floor)
    if len(at) > k:
        named, own = np.unique(ids[at], return_inverse=True)
        top = np.full(len(named), -np.inf)
        np.maximum.at(top, own, score[at])
        if len(named) > k:
            floor = np.partition(top, -k)[-k]
        # a hair below the bound, so that rounding loses no tie
        at = at[(score[at] >= floor - 1e-9 * (1 + abs(floor))) & (score[at] >= top[own])]
    return at


def usable(df: DataFrame, key: str, vector: str) -> DataFrame:
    """``vec_id`` and ``v`` (array of double, or of float where it is one) of the rows that take part."""
    v = F.col(vector)
    if df.schema[vector].dataType.simpleString() != "array<float>":
        v = v.cast("array<double>")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return df.select(F.col(key).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & fine)


def search(df: DataFrame, is_query: Column, key: str = "vec_id", vector: str = "embedding", k: int = 20, trees: int = TREES, leaf: int = LEAF, recall: float = RECALL, visits: int | None = None, fit_values: int = FIT_VALUES, block: int = BLOCK, query_block: int = QUERY_BLOCK) -> DataFrame:
    """``query_id``, ``rank``, ``vec_id`` and ``score`` of the ``k`` nearest rows found for each row where ``is_query``
    (a condition on ``vec_id``, which is what the key is called inside)."""
    spark = df.sparkSession
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = usable(df, key, vector).distinct()
    queries = settled(rows.where(is_query).groupBy("vec_id").agg(F.min("v").alias("v")))
    of_vector = F.row_number().over(Window.partitionBy("v").orderBy("vec_id"))
    rows = settled(rows.withColumn("no", of_vector).where(F.col("no") <= k + 1).drop("no"))
    dim, n = rows.agg(F.max(F.size("v")), F.count("*")).first()
    dim = max(dim or 0, queries.agg(F.max(F.size("v"))).first()[0] or 0)
    if not n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    portion = min(1.0, fit_values / dim / n)
    drawn = rows.where(F.pmod(F.xxhash64("vec_id", "v"), F.lit(1 << 30)) < int(portion * (1 << 30))) if portion < 1 else rows
    drawn = drawn.toArrow().sort_by("vec_id")
    sample, names = matrix(drawn["v"], dim), drawn["vec_id"].to_numpy()
    fitted = Forest(sample, n, trees, leaf)
    least = -(-AT_LEAST * k * fitted.leaves // n)
    visits = min(fitted.leaves, visits or max(least, fitted.needed(sample, names, k, recall)))
    forest = share(spark, fitted)
    by_leaf = fitted.place(sample)
    floors = share(spark, (sample.astype(np.float32) if str(drawn["v"].type.value_type) == "float" else sample, names, by_leaf))

    def put(batches):
        f = held(forest)
        for batch in batches:
            place = f.place(matrix(batch.column(1), dim))
            leaves = pa.ListArray.from_arrays(pa.array(np.arange(0, place.size + 1, f.trees), pa.int32()), pa.array(place.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), leaves], names=["vec_id", "v", "leaves"])

    kind = rows.schema["v"].dataType.simpleString()
    indexed = settled(rows.mapInArrow(put, f"vec_id long, v {kind}, leaves array<int>")).withColumn("leaf", F.explode("leaves"))
    sizes = np.zeros(fitted.leaves, np.int64)
    for r in indexed.groupBy("leaf").count().collect():  # as many rows as the forest has leaves
        sizes[r[0]] = r[1]
    # parts: runs of leaves with one block of vectors or so; a larger leaf is a part of its own, of several groups
    part = np.zeros(fitted.leaves, np.int64)
    room, now = block, 0
    for i, s in enumerate(sizes.tolist()):
        if i and s > room:
            now, room = now + 1, block
        part[i], room = now, room - s
    begins = np.searchsorted(part, np.arange(now + 2))
    groups = np.maximum(1, -(-np.add.reduceat(sizes, begins[:-1]) // (2 * block)))
    parts = share(spark, begins)

    def walker(depth: int):
        def walk(batches):
            f, begins, (fx, fid, fleaf) = held(forest), held(parts), held(floors)
            for batch in batches:
                for at in range(0, batch.num_rows, 128):
                    some = batch.slice(at, 128)
                    q, own = matrix(some.column(1), dim), some.column(0).to_numpy(zero_copy_only=False)
                    visited = f.visited(q, depth)
                    which, where, bits, low = [], [], [], []
                    for i in range(len(q)):
                        here = np.flatnonzero(visited[i][fleaf].any(1) & (fid != own[i]))
                        score = fx[here].astype(np.float64) @ q[i]
                        best = best_ids(score, fid[here], k, -np.inf)
                        few = len(np.unique(fid[here][best])) < k
                        floor = -np.inf if few else score[best].min() - 1e-6 * (1 + np.abs(score[best]).max())
                        there = np.flatnonzero(np.add.reduceat(visited[i], begins[:-1]))
                        which += [i] * len(there)
                        where += there.tolist()
                        low += [floor] * len(there)
                        bits += [np.packbits(visited[i, begins[p] : begins[p + 1]]).tobytes() for p in there]
                    yield pa.RecordBatch.from_arrays([some.column(0).take(which), pa.array(low, pa.float64()), pa.array(where, pa.int32()), pa.array(bits, pa.binary()), some.column(1).take(which)], names=["query_id", "floor", "part", "bits", "q"])

        return walk

    out_schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def meet(ask: pa.Table, member: pa.Table) -> pa.Table:
        """Every query of a part with the vectors of the leaves it visits there."""
        a, b, s = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        if ask.num_rows and member.num_rows:
            begins, p = held(parts), ask["part"][0].as_py()
            x, ids, leaf = matrix(member["v"], dim), member["vec_id"].to_numpy(), member["leaf"].to_numpy() - begins[p]
            q, own, floor, bits = matrix(ask["q"], dim), ask["query_id"].to_numpy(), ask["floor"].to_numpy(), ask["bits"].to_pylist()
            width = int(begins[p + 1] - begins[p])
            for at in range(0, len(q), 256):
                rough = q[at : at + 256] @ x.T
                for i, row in enumerate(rough):
                    visited = np.unpackbits(np.frombuffer(bits[at + i], np.uint8), count=width).view(bool)
                    here = np.flatnonzero(visited[leaf] & (row >= floor[at + i]) & (ids != own[at + i]))
                    here = here[best_ids(row[here], ids[here], k, -np.inf)]
                    a.append(np.full(len(here), own[at + i]))
                    b.append(ids[here])
                    s.append(inner(np.broadcast_to(q[at + i], (len(here), dim)), x[here]))
        return pa.Table.from_arrays([pa.array(np.concatenate(c)) for c in (a, b, s)], schema=out_schema)

    keys = ["part", "sub", "slice"]
    numbers = lambda count: F.explode(F.sequence(F.lit(0).cast("long"), F.col(count).cast("long") - 1))

    def found(asking: DataFrame, depth: int) -> DataFrame:
        asked = settled(asking.repartition(tasks, "vec_id").mapInArrow(walker(depth), f"query_id long, floor double, part int, bits binary, q {kind}"))
        asks = {r[0]: r[1] for r in asked.groupBy("part").count().collect()}  # as many rows as parts
        deal = spark.createDataFrame([(p, int(groups[p]), -(-asks[p] // query_block)) for p in asks], "part int, subs int, slices int")
        leaves = spark.createDataFrame([(int(i), int(part[i])) for i in np.flatnonzero(np.isin(part, list(asks)))], "leaf int, part int")
        dealt = F.broadcast(deal)  # bounded by the leaves of the forest, as is the next
        member = indexed.join(F.broadcast(leaves), "leaf").join(dealt, "part")
        member = member.select("part", F.pmod(F.xxhash64("vec_id", "v"), F.col("subs")).alias("sub"), numbers("slices").alias("slice"), "leaf", "vec_id", "v")
        ask = asked.join(dealt, "part").select("part", numbers("subs").alias("sub"), F.pmod(F.xxhash64("query_id"), F.col("slices")).alias("slice"), "query_id", "floor", "bits", "q")
        met = ask.repartition(tasks, *keys).groupBy(*keys).cogroup(member.repartition(tasks, *keys).groupBy(*keys)).applyInArrow(meet, "query_id long, vec_id long, score double")
        best = met.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        return settled(best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score"))

    first = found(queries, visits)
    full = first.where(F.col("rank") == k).select(F.col("query_id").alias("vec_id"))
    again = queries.join(full, "vec_id", "left_anti")
    if visits >= fitted.leaves or again.isEmpty():
        return first
    return first.join(full.withColumnRenamed("vec_id", "query_id"), "query_id", "left_semi").unionByName(found(again, fitted.leaves))


def op10_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 nearest rows, by inner product, of every row whose id is divisible by 20."""
    return search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
