"""Sharding, WARC, SimHash, line dedup, decontamination, neighbours and the pipeline."""

import hashlib
import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from driftks.llm import components, decontaminate, line_dedup, near_copies, neighbors, sharding, simhash, warc
from driftks.llm.tables import joined_unique, settled, shared_folder, table

from ..conftest import same_rows
from .helpers import ODD_KEYS, SMALL, keys, odd_documents


@pytest.mark.parametrize("n", [1, 2, 3, 5, 16, 17, 1000, 4097])
def test_permutation(n):
    p = sharding.permuted(np.arange(n), n, 20)
    assert sorted(p) == list(range(n)) and (sharding.original(p, n, 20) == np.arange(n)).all()


def test_shards(spark):
    texts = dict(table(spark, SMALL, "documents").select("doc_id", "text").collect())
    rows = sharding.op2_feistel_shards(spark, SMALL).collect()
    assert sorted(r.doc_id for r in rows) == sorted(texts)
    for r in rows:
        raw = (texts[r.doc_id] or "").encode()
        assert (r["size"], r.text_crc32, r.grown_shard) == (len(raw) + 1, zlib.crc32(raw), None)
    slots = {s: sorted(r.slot for r in rows if r.shard == s) for s in range(16)}
    assert all(v == list(range(len(v))) for v in slots.values())
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1
    odd = odd_documents(spark)
    assert keys(sharding.plan_shards(odd, 3)) == ODD_KEYS and sharding.plan_shards(odd.limit(0)).count() == 0
    again = sharding.plan_shards(odd.repartition(5), 3)
    assert sorted(map(str, again.collect())) == sorted(map(str, sharding.plan_shards(odd, 3).collect()))


def feistel(x, n, seed):
    """The permutation once more, one number at a time."""
    bits = 1
    while 4**bits < n:
        bits += 1
    mask = (1 << bits) - 1
    while True:
        left, right = x >> bits, x & mask
        for key in np.random.SeedSequence(seed).generate_state(6, np.uint64):
            m = (right + int(key)) * 0x9E3779B97F4A7C15 % 2**64
            m = (m ^ (m >> 29)) * 0xBF58476D1CE4E5B9 % 2**64
            left, right = right, left ^ ((m ^ (m >> 32)) & mask)
        x = left << bits | right
        if x < n:
            return x


def test_shard_and_slot_of_every_row(spark):
    rows, order = sharding.op2_feistel_shards(spark, SMALL).collect(), {}
    for r in rows:
        h = 42
        for c in (r.doc_id, r["size"], r.text_crc32):
            h = xxhash.xxh64_intdigest(c.to_bytes(8, "little"), h)
        order[r.doc_id] = ((h - 2**64 if h >> 63 else h) % 4096, r.doc_id, r["size"], r.text_crc32)
    for number, key in enumerate(sorted(order, key=order.get)):
        place = feistel(number, len(rows), 20)
        r = next(x for x in rows if x.doc_id == key)
        assert (r.row, r.shard, r.slot) == (number, place % 16, place // 16)


def test_a_run_of_equal_rows_needs_no_array(spark):
    """300,000,000 copies of one row beside others: numbered without gaps, by many tasks."""
    many = spark.range(0, 300_000_000, 1, 8).select(F.lit(7).cast("long").alias("k")).union(spark.range(1000).select("id"))
    rows, n = sharding.numbered(many)
    assert n == 300_001_000
    got = rows.agg(F.count("*"), F.min("row"), F.max("row"), F.sum("row"), F.count_if(F.col("k") == 7)).first()
    assert tuple(got) == (n, 0, n - 1, n * (n - 1) // 2, 300_000_001)
    small, _ = sharding.numbered(spark.range(10).select((F.col("id") % 2).alias("k")), chunk=2)
    assert sorted(r["row"] for r in small.collect()) == list(range(10))


def test_warc_round_trip(spark):
    x = "y" * 1200
    rows = [(1, "u", x), (2, None, x), (3, "v", x + "\r\n\r\nWARC/1.1"), (4, "a\nb", None), (5, "a", ""), (6, "w", "z" * 999), (7, "w", "z" * 999), (None, "q", x), (8, "v2", "é" * 700), (2, None, x)]
    df = spark.createDataFrame([(*r, "c") for r in rows], "page_id long, url string, html string, digest string")
    folder = shared_folder(spark, "warc-test")
    warc.write(df, folder, per_file=2)
    out = warc.resolved(warc.read_headers(spark, folder)).collect()
    assert len(out) == len(rows) and all(r.intact for r in out)
    body = {(r[0], r[1] if r[0] is None else None): (r[2] or "").encode() for r in rows}
    for r in out:
        want = body[(r.page_id, "q" if r.page_id is None else None)]
        assert (r.payload_bytes, r.payload_digest) == (len(want), hashlib.sha1(want).hexdigest())
    assert [(r.page_id, r.refers_to) for r in out if r.record_type == "revisit"] == [(1, 2)]
    empty = shared_folder(spark, "warc-empty")
    warc.write(df.limit(0), empty)
    assert warc.read_headers(spark, empty).count() == 0


def test_warc_query(spark, duck):
    same_rows(warc.op5_warc_revisits(spark, "/root/testdata/sf0.01"), duck, warc.OP5_SQL)


def test_large_payloads_and_many_revisits(spark):
    rows = [(i, f"u{i}", "a" * 1500 if i % 3 else str(i) * 400_000) for i in range(30)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = []
    for few in (0, 1000):
        folder = shared_folder(spark, "warc-large")
        warc.write(df, folder, per_file=4, few=few)
        out = warc.resolved(warc.read_headers(spark, folder)).collect()
        assert len(out) == 30 and all(r.intact for r in out) and len({r.file for r in out}) >= 5
        got.append(sorted((r.page_id, r.record_type, r.refers_to, r.payload_bytes) for r in out))
    assert got[0] == got[1] and sum(r[1] == "revisit" for r in got[0]) == 19


def test_hot_keys_meet_by_broadcast(spark):
    left = settled(spark.range(1000).select(F.when(F.col("id") >= 900, F.col("id") % 7).alias("k"), "id").union(spark.range(500).select(F.lit(3), "id")))
    right = spark.createDataFrame([(i, i * i) for i in range(6)], "k long, v long")
    want = sorted(map(str, left.join(right, ["k"], "left").collect()))
    assert sorted(map(str, joined_unique(left, right, ["k"], 10, 5).collect())) == want
    assert sorted(map(str, joined_unique(left, right, ["k"]).collect())) == want


def closure(ids, linked):
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for a, b in linked:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_components(spark):
    r = random.Random(1)
    edges = [(r.randrange(300), r.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)]
    got = {x.node: x.root for x in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    want = closure({i for e in edges for i in e}, edges)
    assert all(got.get(i, i) == want[i] for i in want)
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.mark.parametrize("bits", [2, 3])
@pytest.mark.parametrize("crowd", [2, 64])
def test_links_are_complete(spark, bits, crowd):
    r = random.Random(bits)
    fps = set()
    for _ in range(25):
        base = r.getrandbits(64)
        for _ in range(r.choice([1, 3, 12])):
            x = base
            for _ in range(r.randrange(4)):
                x ^= 1 << r.randrange(64)
            fps.add(x - (1 << 64) if x >> 63 else x)
    fps = sorted(fps)
    df = spark.createDataFrame([(f,) for f in fps], "fp long")
    found = [tuple(x) for x in simhash.links(df, bits, crowd).collect()]
    far = lambda a, b: ((a ^ b) & (2**64 - 1)).bit_count()
    true = [(a, b) for i, a in enumerate(fps) for b in fps[i + 1 :] if far(a, b) <= bits]
    assert all(far(a, b) <= bits for a, b in found)
    assert closure(fps, found) == closure(fps, true)


def test_simhash_query_equals_brute_force(spark):
    rows = simhash.op7_simhash_components(spark, SMALL).collect()
    fps = {r.doc_id: int(r.fingerprint, 16) for r in rows}
    ids = sorted(fps)
    want = closure(ids, [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if (fps[a] ^ fps[b]).bit_count() <= 2])
    assert {r.doc_id: r.component_id for r in rows} == want
    # every fingerprint once more, one shingle and one bit at a time
    for doc_id, text in table(spark, SMALL, "documents").select("doc_id", "text").collect():
        words = [w for w in re.split("[ \\t-\\r]+", "".join(c.lower() if c.isascii() else c for c in text or "")) if w]
        parts = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)] * bool(words)
        hashes = Counter(xxhash.xxh64_intdigest(p.encode(), 42) for p in parts)
        assert fps[doc_id] == sum(1 << b for b in range(64) if 2 * sum(c for h, c in hashes.items() if h >> b & 1) > len(parts))
    # the fingerprint, with Spark's own hash
    native = spark.sql("select xxhash64('the big cat') as h").first().h % (1 << 64)
    assert simhash.fingerprint("The  BIG\tcat", 3) == native and simhash.fingerprint("the big cat", 5) == native and simhash.fingerprint(" ", 3) == 0
    odd = odd_documents(spark)
    assert keys(simhash.near_duplicates(odd)) == ODD_KEYS and simhash.near_duplicates(odd.limit(0)).count() == 0


def one_edit(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    a, b = sorted((a, b), key=len)
    i = 0
    while i < len(a) and a[i] == b[i]:
        i += 1
    return a[i + 1 :] == b[i + 1 :] if len(a) == len(b) else a[i:] == b[i + 1 :]


def test_line_dedup_equals_brute_force(spark):
    r = random.Random(3)
    base = ["the quick brown fox jumps over it", "pack my box with five dozen liquor jugs and some more words to make it rather long indeed", "x" * 64, "0123456789" * 7]
    docs = {}
    for i in range(200):
        s = list(r.choice(base))
        for _ in range(r.randint(0, 2)):
            k, o = r.randrange(len(s)), r.randrange(3)
            s[k : k + (o != 1)] = [] if o == 2 else [r.choice("abé")]
        docs.setdefault(i // 4, []).append("".join(s))
    rows = [(i, "\n".join(x)) for i, x in docs.items()] + [(99, None), (98, ""), (None, "the quick brown fox jumps over it\nshort")]
    df = spark.createDataFrame([(*x, 1, 2) for x in rows], "doc_id long, text string, place int, n int")
    got = {x.doc_id: x.text for x in line_dedup.clean(df).collect()}
    seen, want = [], {}
    for i, text in sorted(rows, key=lambda x: -1 if x[0] is None else x[0]):
        stay = []
        for line in (text or "").split("\n"):
            if len(line) < line_dedup.LEAST or not any(one_edit(line, s) for s in seen):
                stay.append(line)
            if len(line) >= line_dedup.LEAST:
                seen.append(line)
        want[i] = "\n".join(stay)
    assert got == want
    odd = odd_documents(spark)
    own = {"counts": ("was", "stays")}
    assert keys(line_dedup.clean(odd, **own)) == ODD_KEYS and line_dedup.clean(odd.limit(0), **own).count() == 0


def test_one_edit_equals_brute_force(spark):
    r = random.Random(8)
    rows = [("", ""), ("a", ""), ("", "ab"), ("ab", "ba"), ("x" * 64, "x" * 65), ("x" * 64, "x" * 66)]
    for _ in range(600):
        a = "".join(r.choices("ab😀", k=r.choice([1, 2, 31, 32, 33, 64, 65, 90])))
        b = list(a)
        for _ in range(r.randint(0, 2)):
            k, o = r.randrange(len(b) + 1), r.randrange(3)
            b[k : k + (o != 1)] = [] if o == 2 else [r.choice("abc")]
        rows.append((a, "".join(b)))
    df = spark.createDataFrame([(i, *x) for i, x in enumerate(rows)], "i int, a string, b string")
    got = {x.i: x.ok for x in df.select("i", line_dedup.within_one_edit(F.col("a"), F.col("b")).alias("ok")).collect()}
    assert got == {i: one_edit(*x) for i, x in enumerate(rows)}


def test_line_dedup_of_very_long_lines(spark):
    """Two megabytes in one line, one character changed, and one left out: work must not grow with the square."""
    r = random.Random(6)
    a = "".join(r.choices("abcdefgé ", k=2_000_000)).strip()
    m = len(a) // 2
    df = spark.createDataFrame([(1, a), (2, a[:m] + "#" + a[m + 1 :]), (3, a[:m] + a[m + 1 :])], "doc_id long, text string")
    began = time.perf_counter()
    assert {x.doc_id: x.kept for x in line_dedup.clean(df).collect()} == {1: 1, 2: 0, 3: 0}
    assert time.perf_counter() - began < 40


def test_line_dedup_lengths_and_names(spark):
    df = spark.createDataFrame([(1, "a\nb\na"), (2, "a\nc")], "doc_id long, text string")
    assert {x.doc_id: x.text for x in line_dedup.clean(df, least_exact=1).collect()} == {1: "a\nb", 2: "c"}
    with pytest.raises(ValueError):
        line_dedup.clean(df.withColumn("lines", F.lit(7)))


def test_line_dedup_of_a_long_document(spark):
    lines = [hashlib.sha1(str(i).encode()).hexdigest() for i in range(20_000)]
    df = spark.createDataFrame([(1, "\n".join(lines)), (2, "\n".join([*lines[5:9], "short", lines[0][1:], "a line of its own here"]))], "doc_id long, text string")
    got = {r.doc_id: (r.text, r.lines, r.kept) for r in line_dedup.clean(df).collect()}
    assert got == {1: ("\n".join(lines), 20_000, 20_000), 2: ("short\na line of its own here", 7, 2)}


def test_line_dedup_query(spark, duck):
    same_rows(line_dedup.op8_line_dedup(spark, "/root/testdata/sf0.01"), duck, line_dedup.OP8_SQL)


def aligned(a, b):
    h, best = np.zeros((len(a) + 1, len(b) + 1)), 0.0
    for i in range(1, len(a) + 1):
        for j in range(1, len(b) + 1):
            h[i, j] = max(0, h[i - 1, j - 1] + (1 if a[i - 1] == b[j - 1] else -0.5), h[i - 1, j] - 0.5, h[i, j - 1] - 0.5)
            best = max(best, h[i, j])
    return best


def test_alignment():
    r = np.random.default_rng(0)
    a = [r.integers(0, 5, r.integers(3, 12)).astype(np.uint64) for _ in range(100)]
    b = [r.integers(0, 5, r.integers(3, 20)).astype(np.uint64) for _ in range(100)]
    assert decontaminate.align(a, b)[0] == pytest.approx([aligned(x, y) for x, y in zip(a, b, strict=True)])


def test_edited_passages_are_found(spark):
    r = random.Random(7)
    word = lambda: "".join(r.choices("abcdefghijklmnop", k=r.randint(3, 8)))
    items = [(i, " ".join(word() for _ in range(r.randint(14, 60)))) for i in range(30)] + [(98, None), (99, "too short")]
    docs, planted = [], set()
    for d in range(120):
        words = [word() for _ in range(300)]
        if d % 3 == 0:
            i, text = items[r.randrange(30)]
            copy = [w if r.random() > 0.1 else word() for w in text.split()]
            if d % 2:
                del copy[len(copy) // 2]
            words[100:100] = copy
            planted.add((d, i))
        docs.append((d, " ".join(words).title() if d % 4 == 0 else ", ".join(words)))
    docs += [(500, None), (501, ""), (None, items[3][1])]
    planted.add((None, 3))
    x = spark.createDataFrame([(*d, 0.5) for d in docs], "doc_id long, text string, score double")
    y = spark.createDataFrame(items, "item_id long, text string")
    for block in (10**6, 2500):
        found = decontaminate.passages(x, y, block_bytes=block).collect()
        assert {(f.doc_id, f.item_id) for f in found} == planted
    leak = decontaminate.leak_score(x, y, "leak").where("leak > 0")
    assert {r.doc_id for r in leak.collect()} == {d for d, _ in planted}
    assert decontaminate.passages(x.limit(0), y).count() == 0 and decontaminate.passages(x, y.limit(0)).count() == 0
    one = next(f for f in found if f.doc_id is None)
    assert (one.score, one.start, one.end) == (1.0, 0, len(items[3][1]))


def passages_by_hand(docs, items):
    """Every (document, item) whose best local alignment reaches the least score, from all words of both."""
    words = lambda t: [zlib.crc32(w.encode()) for w in re.findall(r"[0-9a-z\x80-\U0010ffff]+", t.lower())]
    out = set()
    for i, text in items:
        a = np.array(words(text), np.uint64)
        for d, body in docs:
            b = np.array(words(body), np.uint64)
            if len(a) >= 3 and len(b) and len(np.intersect1d(a, b)) >= len(a) / 2:
                if decontaminate.align([a], [b])[0][0] >= 0.5 * len(a):
                    out.add((d, i))
    return out


def test_decontamination_query_equals_brute_force(spark):
    """All documents against all items, every word of both aligned, without seeds, windows or blocks."""
    docs = [(r[0], r[1] or "") for r in table(spark, SMALL, "documents").select("doc_id", "text").collect()]
    items = [(r[0], r[1] or "") for r in table(spark, SMALL, "benchmark").select("item_id", "text").collect()]
    got = {(r.doc_id, r.item_id) for r in decontaminate.op3_decontamination(spark, SMALL).collect()}
    want = passages_by_hand(docs, items)
    assert got <= want and len(got) >= 0.98 * len(want) > 0


def test_passages_beside_each_other_are_all_found():
    r = random.Random(12)
    item = " ".join(f"w{r.randrange(10**6)}" for _ in range(20))
    m = decontaminate.Matcher([1], [item])
    pair = f"{item} {item}"
    assert [(x[1], x[3], x[4]) for x in m.match([pair])] == [(0, 0, len(item)), (0, len(item) + 1, len(pair))]
    noisy = f"é {item} {' '.join(item.split()[5:9])} x {item}"
    assert len(m.match([noisy])) == 2 and noisy[m.match([noisy])[0][3] : m.match([noisy])[0][4]] == item


def test_periodic_texts_take_little_memory():
    import subprocess
    import sys

    code = """
import resource, time
from driftks.llm import decontaminate
m = decontaminate.Matcher([1], ["same " * 20])
began = time.perf_counter()
found = m.match(["same " * 180_000, *["some other words"] * 255, "x " * 3_000_000])
assert 8900 <= len(found) <= 9000, len(found)
print(time.perf_counter() - began, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024)
import driftks.plans.shipping
from pyspark import cloudpickle
assert len(cloudpickle.dumps(decontaminate.Matcher([1], ["a b c d e f g h"]))) < 1_000_000
"""
    said = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True, timeout=120).stdout
    seconds, mb = map(float, said.split())
    assert seconds < 30 and mb < 900


def test_decontamination_query_finds_whole_items(spark):
    docs = table(spark, SMALL, "documents").select("doc_id", "text").collect()
    items = table(spark, SMALL, "benchmark").collect()
    whole = {(d.doc_id, i.item_id) for d in docs for i in items if i.text in (d.text or "")}
    assert whole <= {(r.doc_id, r.item_id) for r in decontaminate.op3_decontamination(spark, SMALL).collect()}


def test_neighbours_recall_and_ties(spark):
    got = neighbors.op10_nearest_neighbours(spark, "/root/testdata/sf0.1").toPandas()
    e = table(spark, "/root/testdata/sf0.1", "embeddings").toPandas().sort_values("vec_id")
    x, ids = np.array(e.embedding.tolist(), float), e.vec_id.to_numpy()
    hits = []
    for q in ids[ids % 20 == 0]:
        s = x @ x[ids == q][0]
        s[ids == q] = -9
        mine = got[got.query_id == q].sort_values("rank")
        hits.append(len(set(mine.vec_id) & set(ids[np.lexsort((ids, -s))[:20]])) / 20)
        assert list(mine["rank"]) == list(range(1, 21)) and (np.diff(mine.score) <= 0).all()
    assert np.mean(hits) >= 0.9
    rows = [(i, [float(i % 7), 1.0]) for i in range(60)] + [(100, None), (120, [0.0, 0.0]), (140, [float("nan"), 1.0]), (160, [1.0]), (None, [1.0, 1.0]), (180, [5.0, None]), (7, [0.0, 1.0])]
    d = spark.createDataFrame([(*r, 1) for r in rows], "vec_id long, embedding array<double>, score int")
    for options in ({}, {"block": 8, "leaf": 8, "query_block": 1}, {"visits": 1, "leaf": 4}):
        out = neighbors.search(d, F.col("vec_id") % 20 == 0, **options).orderBy("query_id", "rank").collect()
        assert {r.query_id for r in out} == {0, 20, 40, 160} and len(out) == 80
        if "visits" in options:
            continue
        # the short vector counts as [1, 0]
        assert [(r.vec_id, r.score) for r in out if r.query_id == 160] == sorted(((i, float(i % 7)) for i in range(60)), key=lambda t: (-t[1], t[0]))[:20]
        top = [(r.vec_id, r.score) for r in out if r.query_id == 20]
        true = sorted(((i, 6.0 * (i % 7) + 1.0) for i in range(60) if i != 20), key=lambda t: (-t[1], t[0]))[:20]
        assert top == true
    assert neighbors.search(d.limit(0), F.col("vec_id") % 20 == 0).count() == 0


def test_neighbours_with_repeated_ids(spark):
    r = np.random.default_rng(4)
    rows = [(i, v.tolist()) for i, v in enumerate(r.normal(size=(100, 4)))]
    rows += [(500, [9.0, 9.0, 9.0, 9.0])] * 30 + [(600, [9.0, 9.0, 9.0, 9.0 + i / 100]) for i in range(30)]
    x = {}
    for i, v in rows:
        x.setdefault(i, []).append(np.array(v))
    d = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    out = neighbors.search(d, F.col("vec_id").isin(20, 40, 60)).orderBy("query_id", "rank").collect()
    for q in (20, 40, 60):
        best = {i: max(float(v @ x[q][0]) for v in vs) for i, vs in x.items() if i != q}
        assert [o.vec_id for o in out if o.query_id == q] == sorted(best, key=lambda i: (-best[i], i))[:20]


def test_neighbours_of_structured_data_take_few_leaves(spark):
    r = np.random.default_rng(9)
    centres = r.normal(size=(300, 32))
    x = np.repeat(centres, 20, axis=0) + 0.15 * r.normal(size=(6000, 32))
    forest = neighbors.Forest(x, len(x))
    assert forest.needed(x, np.arange(len(x)), 20, 0.96) < 0.15 * forest.leaves
    d = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(i, x[0].tolist()) for i in range(6000, 7000)], "vec_id long, embedding array<double>")
    got, hits = neighbors.search(d, F.col("vec_id") % 100 == 0).toPandas(), []
    whole = np.vstack([x, np.repeat(x[:1], 1000, axis=0)])
    for q, rows in got.groupby("query_id"):
        s = whole @ whole[q]
        s[q] = -np.inf
        hits.append(len(set(rows.vec_id) & set(np.lexsort((np.arange(7000), -s))[:20])) / 20)
        assert np.allclose(rows.score, s[rows.vec_id])
    assert len(hits) == 70 and np.mean(hits) >= 0.9


def test_pipeline_stages(spark):
    odd = odd_documents(spark).drop("hash")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, odd, SMALL)
        assert out.columns == (["doc_id", "n_tokens", "ids"] if name == "bpe_encoding" else odd.columns)
        if name != "bpe_encoding":
            assert out.schema == odd.schema and out.select("lines", "kept", "n").distinct().collect() == [(-1, -1, -1)]
        assert out.count() <= 8 and stage(spark, odd.limit(0), SMALL).count() == 0
        if name != "bpe_encoding":
            with pytest.raises(ValueError):
                stage(spark, odd.withColumn("__row", F.lit(1)), SMALL)
    assert keys(corpus_pipeline.without_toxic(spark, odd, SMALL)) == ODD_KEYS
    assert keys(corpus_pipeline.encoded(spark, odd, SMALL)) == ODD_KEYS
    left = corpus_pipeline.without_near_copies(spark, odd, SMALL).collect()
    assert sorted(str(r.doc_id) for r in left) == ["1", "2", "4", "6", "None"]
    assert {r.doc_id for r in corpus_pipeline.without_leaks(spark, odd, SMALL).collect()} == set(ODD_KEYS)


def test_pipeline_keeps_clean_documents(spark):
    docs = table(spark, SMALL, "documents")
    out = corpus_pipeline.run(spark, SMALL)
    assert out.columns == ["doc_id", "n_tokens", "ids"]
    ids = [r.doc_id for r in out.select("doc_id").collect()]
    assert len(ids) == len(set(ids)) and len(ids) > docs.count() // 2


def edited(r, words, edits):
    out = list(words)
    for i in r.sample(range(len(out)), edits):
        out[i] = f"new{r.randrange(10**9)}"
    return out


def shingles(text):
    w = text.split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def jaccard(a, b):
    return len(a & b) / len(a | b)


@pytest.mark.parametrize("crowd", [4, 64])
def test_near_copies_at_similarity_of_four_fifths(spark, crowd):
    r = random.Random(11)
    texts = []
    for _ in range(60):
        base = [f"w{r.randrange(10**6)}" for _ in range(200)]
        texts += [" ".join(base)] + [" ".join(edited(r, base, r.choice([1, 2, 3, 4, 5, 6, 9]))) for _ in range(2)]
    base = [f"w{r.randrange(10**6)}" for _ in range(150)]
    texts += [" ".join(edited(r, base, r.choice([0, 1, 1, 2, 4, 5]))) for _ in range(90)]
    sets = [shingles(t) for t in texts]
    true = [(i, j) for i in range(len(texts)) for j in range(i + 1, len(texts)) if jaccard(sets[i], sets[j]) >= 0.8]
    want = closure(range(len(texts)), true)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {x.doc_id for x in near_copies.firsts(df, "doc_id", crowd=crowd).collect()}
    assert got == set(want.values())
    if crowd == near_copies.CROWD:
        assert {x.doc_id for x in corpus_pipeline.without_near_copies(spark, df, SMALL).collect()} == got


def test_no_near_copy_is_lost_in_a_crowd_of_others(spark):
    """Texts that share a long passage, so that index entries are crowded by texts that are no copies; pairs among them are."""
    r = random.Random(5)
    passage, texts = " ".join(f"p{i}" for i in range(150)), []
    for _ in range(200):
        own = [f"w{r.randrange(10**6)}" for _ in range(50)]
        other = [f"e{r.randrange(10**6)}" if i in (7, 20, 33, 46) else w for i, w in enumerate(own)]
        texts += [f"{passage} {' '.join(own)}", f"{passage} {' '.join(other)}"]
    sets = [shingles(t) for t in texts]
    true = [(i, j) for i in range(len(texts)) for j in range(i + 1, len(texts)) if jaccard(sets[i], sets[j]) >= 0.8]
    want = closure(range(len(texts)), true)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {x.doc_id for x in near_copies.firsts(df, "doc_id", crowd=4).collect()} == set(want.values())


def test_variants_are_dealt_to_many_tasks(spark):
    """Fingerprints that are grouped by themselves stay in few tasks; 64 variants of each are made in as many as the session has."""
    fps = spark.range(5_000).select(F.xxhash64("id").alias("fp")).distinct()
    seen, made = [], simhash.variants
    try:
        simhash.variants = lambda df, bits: seen.append(df) or made(df, bits)
        simhash.links(fps).count()
    finally:
        simhash.variants = made
    assert made(seen[0], 2).rdd.getNumPartitions() == int(spark.conf.get("spark.sql.shuffle.partitions"))
