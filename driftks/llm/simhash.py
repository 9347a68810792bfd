"""SimHash near-duplicates through deletion-variant signatures.

A fingerprint is the bitwise majority of the 64-bit hashes of a text's word shingles. Two
fingerprints link if at most ``bits`` of their 64 bits differ. They are cut into
``bits // 2 + 1`` segments: that many segments cannot all differ in two bits or more, so linked
fingerprints have a segment that differs by one bit at most. Every segment is indexed once
for each of its bits, with that bit as a wildcard; an equality join of these variants finds all
candidates and the popcount of the difference verifies them.

An index entry that a whole crowd of fingerprints shares (more than ``crowd``) would be joined
pair by pair. Its members go another exact way instead: each names all points of the cube within
half of ``bits`` (rounded up) of itself. Two that name the same point, one of them within
``bits // 2``, are linked by the triangle inequality, and two linked fingerprints share a point
half way between them; so every member is linked to the least near member of each point it
names and no pairs are listed. Both ways give exactly the same components.

Only distinct fingerprints are indexed, so exact copies cost one entry whatever their number; entries
are counted before they are joined, and those that more than one fingerprint shares are broadcast if there are
``SENT`` of them at most, so the variants are shuffled once, for the counts alone. A fingerprint or component that
holds very many rows gets its answer by broadcast instead of gathering them in one task.

Edge cases: a null or empty text, or one without words, has fingerprint zero and links like any
other; with fewer words than a shingle, the whole sequence is the one shingle; repeated rows
and null ids share their fingerprint's component; other columns are ignored by ``fingerprints``.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.components import components
from driftks.llm.tables import joined_unique, settled, table, whole_text

SEED = 42
SENT = 200_000  # rows of a few numbers (index entries, keys) that are broadcast at most; more are joined by a shuffle


def shingle_hashes(text: str, shingle: int) -> np.ndarray:
    """The 64-bit hash of every word shingle of one text, repeats included."""
    import xxhash

    words = text.encode().lower().split()  # of bytes: A-Z alone are lowered, and ASCII white space splits
    if not words:
        return np.zeros(0, np.uint64)
    parts = [b" ".join(p) for p in zip(*(words[i:] for i in range(shingle)))] or [b" ".join(words)]
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(p, SEED) for p in parts), np.uint64, len(parts))


def majority(hashes: np.ndarray) -> int:
    """The bits that most of the hashes have; zero if there are none."""
    over = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 4096):
        over += np.unpackbits(hashes[i : i + 4096].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * over > len(hashes)).tobytes(), "big")


def fingerprint(text: str, shingle: int) -> int:
    """The 64-bit SimHash of one text, as an unsigned integer."""
    return majority(shingle_hashes(text, shingle))


def fingerprints(df: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 3) -> DataFrame:
    """``key`` and ``fp`` (a long that holds the 64 bits) of every row."""
    kind = df.schema[key].dataType

    def run(batches):
        for batch in batches:
            out = np.array([fingerprint(t, shingle) for t in batch.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.int64())], names=[key, "fp"])

    return df.select(key, whole_text(text).alias("text")).mapInArrow(run, f"`{key}` {kind.simpleString()}, fp long")


def _segments(bits: int) -> list[list[int]]:
    return [list(map(int, s)) for s in np.array_split(np.arange(64), bits // 2 + 1)]


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def variants(fps: DataFrame, bits: int) -> DataFrame:
    """``slot`` (which segment and wildcard), ``part`` (what is left of the segment) and ``fp``."""
    slots = []
    for seg in _segments(bits):
        whole = sum(1 << b for b in seg)
        slots += [_signed(whole & ~(1 << b)) for b in seg]
    each = F.explode(F.transform(F.array(*map(F.lit, slots)), lambda m, i: F.struct(i.alias("slot"), F.col("fp").bitwiseAND(m).alias("part"))))
    return fps.select("fp", each.alias("v")).select(F.col("v.slot").alias("slot"), F.col("v.part").alias("part"), "fp")


def points(fps: DataFrame, bits: int) -> DataFrame:
    """``point`` within half of ``bits`` of ``fp``, and whether it is ``near`` (``bits // 2`` or less away)."""
    far = (bits + 1) // 2
    flips = [(sum(1 << b for b in c), r) for r in range(far + 1) for c in combinations(range(64), r)]
    masks = F.array(*(F.struct(F.lit(_signed(m)).alias("m"), F.lit(r <= bits // 2).alias("near")) for m, r in flips))
    return fps.select("fp", F.explode(F.transform(masks, lambda m: F.struct(F.col("fp").bitwiseXOR(m["m"]).alias("point"), m["near"].alias("near")))).alias("p")).select("p.point", "p.near", "fp")


def links(fps: DataFrame, bits: int = 2, crowd: int = 64) -> DataFrame:
    """Pairs (a, b) of distinct fingerprints whose components are those of all linked pairs."""
    if not 1 <= bits <= 3:
        raise ValueError("between 1 and 3 differing bits")
    # dealt by a hash of its own: by ``fp`` alone, fingerprints that are grouped by it already stay in the few tasks that their size calls for, not their variants'
    each = variants(fps.repartition(int(fps.sparkSession.conf.get("spark.sql.shuffle.partitions")), F.xxhash64("fp")), bits)
    entry = ["slot", "part"]
    counts = settled(each.groupBy(*entry).agg(F.count("*").alias("n")).where("n > 1"))
    shared = settled(each.join(F.broadcast(counts) if counts.count() <= SENT else counts, entry))
    thin = shared.where(F.col("n") <= crowd).drop("n")
    other = thin.withColumnRenamed("fp", "b")
    pairs = thin.withColumnRenamed("fp", "a").join(other, entry).where((F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= bits)).select("a", "b")
    crowded = shared.where(F.col("n") > crowd).select("fp").distinct()
    named = settled(points(crowded, bits))
    least = named.where("near").groupBy("point").agg(F.min("fp").alias("a"))
    stars = named.join(least, "point").where("a <> fp").select("a", F.col("fp").alias("b"))
    return pairs.union(stars).distinct()


def near_duplicates(df: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 3, bits: int = 2) -> DataFrame:
    """``key``, ``fp`` and ``component_id``, the least key that links reach, for every row."""
    rows = settled(fingerprints(df, key, text, shingle))
    per = settled(rows.groupBy("fp").agg(F.min(key).alias("least")))
    roots = components(links(per.select("fp"), bits))
    joined = settled(per.join(roots, per["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root")))
    of_root = joined.groupBy("root").agg(F.min("least").alias("component_id"))
    of_fp = joined_unique(joined, of_root, ["root"]).select("fp", "component_id")
    return joined_unique(rows, of_fp, ["fp"]).select(key, "fp", "component_id")


def op7_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents: 3-word shingles, links at 2 bits or fewer, components named by their least id."""
    out = near_duplicates(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
