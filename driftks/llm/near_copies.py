"""Near copies by the Jaccard similarity of word shingles: MinHash bands for candidates, exact sets for the decision.

Two texts are near copies if their sets of shingles have a similarity of ``LEAST`` or more; groups are the
connected components. Candidates are each text and the least one that links of SimHash fingerprints (at most
``bits`` differing bits) reach from it, and texts that share a MinHash entry: fingerprints of texts at similarity 0.8 differ in some 10 bits, so they alone
catch exact copies and few others.
``BANDS`` bands of ``ROWS`` MinHash values each are index entries; texts that share an entry are candidates. A pair at
similarity s shares one with probability 1 - (1 - s^4)^16: 0.9998 at 0.8, more above. Each candidate
is decided by the sets themselves, so nothing below ``least`` is linked this way.

An entry that more than ``crowd`` sets share is not joined pair by pair at once. First its members meet its leader (the one of
least hash). Its strays are then the members outside its largest component; if they are ``crowd`` at most, they meet all members in other
components. The members of entries with more strays are indexed anew, by the rarest fifth of their shingles and one more: two sets of
similarity 0.8 have one of these in common, so nothing is missed, and what a crowd has in common (a passage, a form) is
not among them. These entries take turns: in each, the strays (or some of them, eight times as many with each turn, drawn by hash) meet all members in other
components and leave the entry, as all their links in it are known. It is done when one component is left.
Members of one component need not meet, so a crowd of copies is done soon, and no link among candidates is missed.

Edge cases: texts with equal sets (all texts without words among them) are one node whatever their number; with fewer
words than a shingle, the whole sequence is the one shingle. Sets are named by a 64-bit hash.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftks.llm import simhash
from driftks.llm.components import components
from driftks.llm.tables import parts, settled, whole_text

BANDS, ROWS = 16, 4
LEAST = (4, 5)  # as a fraction of whole numbers, so that the bound itself is met exactly
CROWD = 64

_R = np.random.default_rng(11)
_FLIPS = _R.integers(0, 1 << 64, BANDS * ROWS, np.uint64)
_TIMES = _R.integers(0, 1 << 64, BANDS * ROWS, np.uint64) | np.uint64(1)
_MIX = _R.integers(0, 1 << 64, (BANDS, ROWS), np.uint64) | np.uint64(1)


def bands(hashes: np.ndarray) -> np.ndarray:
    """The index entries of one set of shingle hashes."""
    low = np.full(BANDS * ROWS, (1 << 64) - 1, np.uint64)
    for i in range(0, len(hashes), 2048):
        low = np.minimum(low, ((hashes[i : i + 2048] ^ _FLIPS[:, None]) * _TIMES[:, None]).min(1))
    return (low.reshape(BANDS, ROWS) * _MIX).sum(1, dtype=np.uint64)


def described(df: DataFrame, key: str, text: str, shingle: int) -> DataFrame:
    """``key``, ``fp`` (SimHash), ``x`` (name of the shingle set), ``size`` of the set and ``entries``."""
    kind = df.schema[key].dataType

    def run(batches):
        import xxhash

        for batch in parts(batches):
            fps, names, sizes, entries = [], [], [], []
            for t in batch.column(1).to_pylist():
                hashes = simhash.shingle_hashes(t, shingle)
                distinct = np.unique(hashes)
                fps.append(simhash.majority(hashes))
                names.append(xxhash.xxh64_intdigest(distinct.tobytes(), simhash.SEED))
                sizes.append(len(distinct))
                entries.append(bands(distinct).view(np.int64))
            longs = [pa.array(np.array(c, np.uint64).view(np.int64), pa.int64()) for c in (fps, names)]
            lists = pa.array(entries, pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), *longs, pa.array(sizes, pa.int32()), lists], names=[key, "fp", "x", "size", "entries"])

    return df.select(key, whole_text(text).alias("text")).mapInArrow(run, f"`{key}` {kind.simpleString()}, fp long, x long, size int, entries array<long>")


def shingle_sets(df: DataFrame, shingle: int) -> DataFrame:
    """``x`` and the set of shingle hashes of every ``text``."""

    def run(batches):
        for batch in parts(batches):
            sets = [np.unique(simhash.shingle_hashes(t, shingle)).view(np.int64) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["x", "shingles"])

    return df.select("x", whole_text("text").alias("text")).mapInArrow(run, "x long, shingles array<long>")


def _comparable(small: str = "a_size", large: str = "b_size"):
    """Sizes that leave room for the least similarity."""
    over, under = LEAST
    return (F.least(small, large) * under >= F.greatest(small, large) * over)


def _side(entries: DataFrame, name: str) -> DataFrame:
    return entries.select("entry", *(F.col(c).alias(name + e) for c, e in (("x", ""), ("size", "_size"), ("root", "_root"), ("pos", "_pos")) if c in entries.columns))


def _pairs(entries: DataFrame) -> DataFrame:
    """Pairs (a, b) of the members (entry, x, size) of each entry."""
    met = _side(entries, "a").join(_side(entries, "b"), "entry")
    return met.where((F.col("a") < F.col("b")) & _comparable()).select("a", "b")


def _met(asked: DataFrame, members: DataFrame) -> DataFrame:
    """Pairs (a, b) of each of ``asked`` (entry, x, size, root) with all ``members`` of its entry in other components."""
    met = _side(asked, "a").join(_side(members, "b"), "entry").where((F.col("a_root") != F.col("b_root")) & _comparable())
    if "pos" in members.columns:  # the first shingle that a pair shares leaves room for the others it must share
        over, under = LEAST
        met = met.where(F.least(F.col("a_size") - F.col("a_pos"), F.col("b_size") - F.col("b_pos")) * (over + under) >= (F.col("a_size") + F.col("b_size")) * over)
    return met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _led(entries: DataFrame) -> DataFrame:
    """Each member (entry, x, size) with the ``leader`` (x, size) of its entry."""
    met = entries.where(F.col("x") != F.col("leader.x")).where(_comparable("size", "leader.size"))
    return met.select(F.col("x").alias("a"), F.col("leader.x").alias("b"))


def _placed(members: DataFrame, links: DataFrame) -> DataFrame:
    """``members`` (entry, x, size) of entries that hold several components, with ``root``, the number of ``strays`` and whether a member is a ``stray``."""
    roots = components(links)
    at = settled(members.drop("root", "strays", "stray").join(roots, F.col("x") == F.col("node"), "left").withColumn("root", F.coalesce("root", "x")).drop("node"))
    per = at.groupBy("entry", "root").agg(F.count("*").alias("c"))
    of = per.groupBy("entry").agg(F.max_by("root", F.struct("c", "root")).alias("main"), (F.sum("c") - F.max("c")).alias("strays")).where("strays > 0")
    return settled(at.join(of, "entry").withColumn("stray", F.col("root") != F.col("main")).drop("main"))


def _whole(named: DataFrame, sets: DataFrame, texts: DataFrame, key: str, shingle: int) -> DataFrame:
    """``x`` and the set of shingle hashes of the sets ``named`` (x)."""
    ask = settled(sets.join(named, "x", "left_semi").select("x", F.col("least").alias("__least")))
    ask = F.broadcast(ask) if ask.count() <= simhash.SENT else ask  # so few leave the texts where they are
    return settled(shingle_sets(texts.join(ask, F.col(key) == F.col("__least")).select("x", "text"), shingle))


def rarest(whole: DataFrame) -> DataFrame:
    """Index entries (entry, x, size, pos) of the sets ``whole`` (x, shingles): those of the rarest shingles of each that no two similar sets can all differ in."""
    over, under = LEAST
    each = whole.select("x", F.size("shingles").alias("size"), F.explode("shingles").alias("entry"))
    known = each.join(each.groupBy("entry").agg(F.count("*").alias("c")), "entry")
    sorted_ = known.groupBy("x", "size").agg(F.array_sort(F.collect_list(F.struct("c", "entry"))).alias("es"))  # of one set
    first = F.col("size") - F.ceil(F.col("size") * over / under).cast("int") + 1
    return sorted_.select("x", "size", F.posexplode(F.slice("es", F.lit(1), first)).alias("pos", "e")).where("e.c > 1").select("e.entry", "x", "size", "pos")


def verified(pairs: DataFrame, sets: DataFrame, texts: DataFrame, key: str, shingle: int) -> DataFrame:
    """Those of ``pairs`` whose sets are similar enough."""
    over, under = LEAST
    pairs = settled(pairs.distinct())
    named = pairs.select(F.col("a").alias("x")).union(pairs.select(F.col("b").alias("x"))).distinct()
    whole = _whole(named, sets, texts, key, shingle)
    side = lambda s: whole.select(F.col("x").alias(s), F.col("shingles").alias(f"{s}_set"))
    met = pairs.join(side("a"), "a").join(side("b"), "b")
    met = met.withColumn("common", F.size(F.array_intersect("a_set", "b_set"))).withColumn("all", F.size("a_set") + F.size("b_set") - F.col("common"))
    return settled(met.where(F.col("common") * under >= F.col("all") * over).select("a", "b"))


def similar(sets: DataFrame, texts: DataFrame, key: str, shingle: int, more: DataFrame, crowd: int = CROWD) -> DataFrame:
    """Pairs (a, b) of ``sets`` (x, size, entries, least) whose components are those of all pairs found; ``more``: further candidates."""
    entries = sets.where("size > 0").select("x", "size", F.explode("entries").alias("entry"))
    leader = F.min_by(F.struct("x", "size"), F.xxhash64("x")).alias("leader")
    counts = entries.groupBy("entry").agg(F.count("*").alias("n"), leader).where("n > 1")
    shared = settled(entries.join(counts, "entry"))
    thin = shared.where(F.col("n") <= crowd).select("entry", "x", "size")
    crowded = shared.where(F.col("n") > crowd)
    if crowded.isEmpty():
        return verified(_pairs(thin).union(more), sets, texts, key, shingle)
    found = verified(_pairs(thin).union(_led(crowded)).union(more), sets, texts, key, shingle)
    members = _placed(crowded, found)
    few, many = members.where(F.col("strays") <= crowd), members.where(F.col("strays") > crowd).select("x").distinct()
    found = settled(found.union(verified(_met(few.where("stray"), few), sets, texts, key, shingle)))
    if many.isEmpty():
        return found
    members, turn = _placed(settled(rarest(_whole(many, sets, texts, key, shingle))), found), crowd
    while not members.isEmpty():
        lot = F.pmod(F.xxhash64(F.lit(turn), "x"), F.lit(1 << 30)) * F.col("strays") < F.lit(turn << 30)
        drawn = members.withColumn("asked", F.col("stray") & ((F.col("strays") <= turn) | lot))
        asked = drawn.where("asked")
        found = settled(found.union(verified(_met(asked, drawn), sets, texts, key, shingle)))
        members, turn = _placed(drawn.where(~F.col("asked") & (F.col("strays") > turn)), found), 8 * turn
    return found


def firsts(df: DataFrame, key: str, text: str = "text", shingle: int = 5, bits: int = 2, crowd: int = CROWD) -> DataFrame:
    """The least ``key`` of every group of near copies; keys must not repeat."""
    texts = df.select(key, F.col(text).alias("text"))
    rows = settled(described(texts, key, "text", shingle))
    sets = settled(rows.groupBy("x").agg(F.min(key).alias("least"), F.first("size").alias("size"), F.first("entries").alias("entries")))
    prints = settled(rows.select("fp", "x").distinct())
    alike = components(simhash.links(prints.select("fp").distinct(), bits))
    named = prints.join(alike, prints["fp"] == alike["node"], "left").select("x", F.coalesce("root", "fp").alias("print"))
    home = named.groupBy("print").agg(F.min("x").alias("home"))
    # one candidate for a set: the least set among the texts that its fingerprint is linked to
    more = named.join(home, "print").where("x <> home").select(F.col("home").alias("a"), F.col("x").alias("b"))
    roots = components(similar(sets, texts, key, shingle, more, crowd))
    joined = sets.join(roots, sets["x"] == roots["node"], "left").select("least", F.coalesce("root", "x").alias("root"))
    return joined.groupBy("root").agg(F.min("least").alias(key)).select(key)
