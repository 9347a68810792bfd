"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment.

One pass counts, over all texts, the n-grams that occur in test items. The rarest half of an item's
n-grams, and all that are rare in themselves (``RARE``, ``FEW``: n-grams that no text holds tell
nothing, so an edited copy may have others only), are its seeds. A second pass joins
every n-gram of every text to the seeds, which are broadcast. Around the hits of an item, along the
diagonal that they give, a window of the text is aligned with the item, word by word, with gaps
(Smith-Waterman: 1 for equal words, -1/2 for a changed, added or missing one). What is left of a window
on either side of its best passage is aligned again, until nothing counts. A passage counts if its
score is at least ``least`` of the item's number of words, so copies with a quarter of their words
edited still count.

Both passes hash whole batches of text as bytes with numpy. Items go to the workers by broadcast in
blocks of at most ``block_bytes`` bytes of text (one item at least); a larger benchmark is worked through
block after block. No text is shuffled. Windows span one item's length of diagonals at most and are aligned
in groups of bounded area, so a periodic text takes no more memory than another.

Edge cases: null and empty texts hold nothing; items with fewer words than a seed are not looked
for; equal items are found each; of overlapping passages of one item in a text the best is
reported, of passages apart all are; texts of any length are read whole; an empty benchmark or
corpus gives an empty result; other columns are ignored. Places are code points of the
lower-cased text, end exclusive.
"""

from __future__ import annotations

from bisect import bisect
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.tables import table, whole_text
from driftks.plans.shipping import held, share

SEED_WORDS = 3
#: An n-gram is rare up to this share of the corpus's n-grams, or up to so many occurrences.
RARE, FEW = 1e-7, 64
LEAST = 0.5
MISS = 0.5
BLOCK_BYTES = 8_000_000
CHUNK = 1_000_000
#: Bytes that are hashed at once (a longer text is cut at a blank), and cells of the windows that are aligned at once.
PIECE, AREA = 4_000_000, 400_000
RADIX = 0x9E3779B97F4A7C15


class Words(NamedTuple):
    """The words of a batch of texts: hash, first byte, byte after, and the text they are of."""

    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    owner: np.ndarray


def _powers(n: int) -> np.ndarray:
    out = np.full(n, RADIX, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_IS_WORD = np.zeros(256, bool)
_IS_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


class _Memory(dict):
    """Tables that every process makes for itself: pickled, it is empty."""

    def __reduce__(self):
        return _Memory, ()


_known = _Memory()


def words_of(texts: list[bytes]) -> Words:
    """Words (runs of letters, digits and other non-ASCII characters but punctuation) of lower-case UTF-8 texts."""
    if len(texts) != 1 or len(texts[0]) <= PIECE:
        return _words(texts)
    text, parts, at = texts[0], [], 0
    while at < len(text):
        end = len(text) if len(text) - at <= PIECE else text.find(b" ", at + PIECE)
        end = len(text) if end < 0 else end
        w = _words([text[at:end]])
        parts.append(Words(w.hash, w.start + at, w.end + at, w.owner))
        at = end
    return Words(*map(np.concatenate, zip(*parts, strict=True)))


def _words(texts: list[bytes]) -> Words:
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    raw = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
    if len(_known.get("p", ())) < len(raw):
        _known["p"] = _powers(max(len(raw), CHUNK * 2))
        _known["i"] = _inverse(_known["p"])
    inside = _IS_WORD[raw]
    # non-ASCII white space and punctuation: U+0080-00BF but letters, U+2000-206F, U+3000-303F
    if (lead := np.flatnonzero((raw == 0xC2) | (raw == 0xE2) | (raw == 0xE3))).size:
        nxt = raw[np.minimum(lead + 1, len(raw) - 1)]
        two = lead[(raw[lead] == 0xC2) & (nxt != 0xAA) & (nxt != 0xB5) & (nxt != 0xBA)]
        three = lead[((raw[lead] == 0xE2) & (nxt >= 0x80) & (nxt <= 0x81)) | ((raw[lead] == 0xE3) & (nxt == 0x80))]
        inside[two] = inside[two + 1] = False
        inside[three] = inside[three + 1] = inside[three + 2] = False
    edge = np.diff(np.concatenate([[0], inside.view(np.int8), [0]]))
    start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    powers, inverse = _known["p"], _known["i"]
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(raw.astype(np.uint64) * powers[: len(raw)])])
    h = (total[end] - total[start]) * inverse[start]
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    begins = np.cumsum(sizes + 1) - sizes - 1
    owner = np.searchsorted(begins, start, side="right") - 1
    return Words(h, start - begins[owner], end - begins[owner], owner)


def _inverse(powers: np.ndarray) -> np.ndarray:
    out = np.full(len(powers), pow(RADIX, -1, 1 << 64), np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


def grams_of(words: Words, n: int = SEED_WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the n-grams that lie in one text, and the number of their first word."""
    m = len(words.hash) - n + 1
    if m <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    h = np.zeros(m, np.uint64)
    for k in range(n):
        h = (h ^ words.hash[k : m + k]) * np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(30)
    at = np.flatnonzero(words.owner[:m] == words.owner[n - 1 :])
    return h[at], at


class Lookup:
    """Membership of hashes in a sorted set, with a bit table in front."""

    def __init__(self, keys: np.ndarray):
        self.keys = np.unique(keys)
        self.bits = max(16, int(len(self.keys)).bit_length() + 4)
        self.table = np.zeros(1 << self.bits, bool)
        self.table[self.keys >> np.uint64(64 - self.bits)] = True

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which of ``hashes`` are keys, and which keys they are."""
        at = np.flatnonzero(self.table[hashes >> np.uint64(64 - self.bits)])
        if not len(at):
            return at, at
        k = np.minimum(np.searchsorted(self.keys, hashes[at]), len(self.keys) - 1)
        there = self.keys[k] == hashes[at]
        return at[there], k[there]


def align(items: list[np.ndarray], windows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Best local alignment of each item with its window: score, and the window word at which it ends."""
    n, rows, cols = len(items), max(map(len, items)), max(map(len, windows))
    a = np.zeros((n, rows), np.uint64)
    b = np.zeros((n, cols), np.uint64)
    there_a, there_b = np.zeros((n, rows), bool), np.zeros((n, cols), bool)
    for k, (x, y) in enumerate(zip(items, windows, strict=True)):
        a[k, : len(x)], b[k, : len(y)] = x, y
        there_a[k, : len(x)], there_b[k, : len(y)] = True, True
    gap = (MISS * np.arange(cols + 1)).astype(np.float32)
    above = np.zeros((n, cols + 1), np.float32)
    best, end = np.zeros(n, np.float32), np.zeros(n, np.int64)
    for i in range(rows):
        same = (a[:, i : i + 1] == b) & there_a[:, i : i + 1] & there_b
        now = np.zeros_like(above)
        now[:, 1:] = np.maximum(above[:, :-1] + np.where(same, np.float32(1), np.float32(-MISS)), above[:, 1:] - MISS)
        np.maximum(now, 0, out=now)
        now = np.maximum.accumulate(now + gap, axis=1) - gap  # a run of added words, from where it began
        top = now.argmax(1)
        value = now[np.arange(n), top]
        better = value > best
        best[better], end[better] = value[better], top[better]
        above = now
    return best, end


class Matcher:
    """The seeds and words of a block of test items; finds their passages in texts."""

    def __init__(self, ids: list, texts: list[str], counts: dict[int, int] | None = None, total: int = 0, least: float = LEAST):
        """``counts``: of each n-gram (by hash) among the ``total`` n-grams of the corpus; None: all are seeds."""
        self.ids, self.least = ids, least
        w = words_of([t.lower().encode() for t in texts])
        bounds = np.searchsorted(w.owner, np.arange(len(texts) + 1))
        self.items = [w.hash[bounds[k] : bounds[k + 1]] for k in range(len(texts))]
        self.lens = np.array(list(map(len, self.items)), np.int64)
        gram, at = grams_of(w)
        keep = np.ones(len(gram), bool)
        if counts is not None and len(gram):
            count = np.array([counts.get(h, 0) for h in gram.tolist()])
            order = np.lexsort((count, w.owner[at]))
            size = np.bincount(w.owner[at], minlength=len(texts))
            rank = np.empty(len(gram), np.int64)
            rank[order] = np.arange(len(gram)) - np.repeat(np.cumsum(size) - size, size)
            keep = (rank < np.maximum(8, (size[w.owner[at]] + 1) // 2)) | (count <= max(FEW, RARE * total))
        gram, at = gram[keep], at[keep]
        self.lookup = Lookup(gram)
        # which (item, place) each seed has
        key = np.searchsorted(self.lookup.keys, gram)
        order = np.argsort(key, kind="stable")
        self.first = np.searchsorted(key[order], np.arange(len(self.lookup.keys) + 1))
        self.seed_item = w.owner[at][order]
        self.seed_place = at[order] - bounds[w.owner[at][order]]

    def match(self, texts: list[str | None]) -> list[tuple[int, int, float, int, int]]:
        """(text, item, score as a share of the item's words, start, end) of every passage."""
        return [(at + t, *rest) for at, raw in portions(texts) for t, *rest in self._chunk(raw)]

    def _chunk(self, raw: list[bytes]) -> list[tuple]:
        w = words_of(raw)
        gram, first = grams_of(w)
        hit, key = self.lookup.find(gram)
        if not len(hit):
            return []
        times = self.first[key + 1] - self.first[key]
        seed = np.repeat(self.first[key], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        word = np.repeat(first[hit], times)
        item, text = self.seed_item[seed], w.owner[word]
        diagonal = word - self.seed_place[seed]
        # neighbouring diagonals of one item in one text make one window, as long as they are within one item's length
        order = np.lexsort((diagonal, item, text))
        item, text, diagonal = item[order], text[order], diagonal[order]
        lens = self.lens
        new = np.ones(len(item), bool)
        new[1:] = (item[1:] != item[:-1]) | (text[1:] != text[:-1]) | (diagonal[1:] - diagonal[:-1] > lens[item[1:]] // 2 + 2)
        chain = np.flatnonzero(new)[np.cumsum(new) - 1]
        stretch = (diagonal - diagonal[chain]) // np.maximum(lens[item], 1)
        new[1:] |= stretch[1:] != stretch[:-1]
        begin = np.flatnonzero(new)
        last = np.append(begin[1:], len(item)) - 1
        bounds = np.searchsorted(w.owner, np.arange(len(raw) + 1))
        slack = lens[item[begin]] // 4 + 2
        low = np.maximum(bounds[text[begin]], diagonal[begin] - slack)
        high = np.minimum(bounds[text[begin] + 1], diagonal[last] + lens[item[begin]] + slack)
        found: dict[tuple[int, int], list[tuple[float, int, int]]] = {}
        todo = np.stack([text[begin], item[begin], low, high], 1)
        while len(todo):
            rest = []
            todo = todo[np.lexsort((todo[:, 3] - todo[:, 2], lens[todo[:, 1]]))]
            for some in _areas(todo):
                items = [self.items[i] for i in some[:, 1]]
                views = [w.hash[a:b] for a, b in some[:, 2:].tolist()]
                score, end = align(items, views)
                good = np.flatnonzero(score >= self.least * lens[some[:, 1]])
                if not len(good):
                    continue
                # the same alignment read backwards ends where it begins
                _, back = align([items[g][::-1] for g in good], [views[g][: end[g]][::-1] for g in good])
                for g, b in zip(good.tolist(), back.tolist(), strict=True):
                    t, i, a, z = some[g].tolist()
                    first, past = a + int(end[g]) - b, a + int(end[g])
                    found.setdefault((t, i), []).append((float(score[g]), first, past))
                    rest += [(t, i, x, y) for x, y in ((a, first), (past, z)) if y - x >= self.least * lens[i]]
            todo = np.array(rest, np.int64).reshape(-1, 4)
        out = []
        for (t, i), passages in found.items():
            for score, a, z in _apart(passages):
                out.append((t, i, score / len(self.items[i]), w.start[a], w.end[z - 1]))
        return _in_characters(raw, sorted(out))


def _areas(todo: np.ndarray) -> Iterator[np.ndarray]:
    """Rows (text, item, first, past) in order of their width, in groups whose padded area is bounded."""
    at, width = 0, todo[:, 3] - todo[:, 2]
    while at < len(todo):
        end, most = at + 1, int(width[at])
        while end < len(todo) and (end + 1 - at) * max(most, int(width[end])) <= AREA:
            most = max(most, int(width[end]))
            end += 1
        yield todo[at:end]
        at = end


def _apart(passages: list[tuple[float, int, int]]) -> list[tuple[float, int, int]]:
    """Of passages that overlap, the best."""
    taken: list[tuple[int, int]] = []
    out = []
    for score, a, z in sorted(set(passages), key=lambda p: (-p[0], p[1], p[2])):
        k = bisect(taken, (a, z))
        if (k == 0 or taken[k - 1][1] <= a) and (k == len(taken) or z <= taken[k][0]):
            taken.insert(k, (a, z))
            out.append((score, a, z))
    return out


def _in_characters(raw: list[bytes], found: list[tuple]) -> list[tuple]:
    """Byte places as places of code points: those that begin before each."""
    out, of, points = [], None, None
    for t, i, score, a, z in found:
        if raw[t].isascii():
            out.append((t, i, score, int(a), int(z)))
            continue
        if of != t:
            of, points = t, np.cumsum((np.frombuffer(raw[t], np.uint8) & 0xC0) != 0x80)
        out.append((t, i, score, int(points[a - 1]) if a else 0, int(points[z - 1])))
    return out


def item_blocks(items: DataFrame, key: str, text: str, block_bytes: int = BLOCK_BYTES) -> Iterator[list]:
    """The test items as lists of rows, each of ``block_bytes`` bytes of text or so, by a hash of (id, text)."""
    rows = items.select(key, whole_text(text).alias("text"))
    size = rows.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    blocks = size // block_bytes + 1
    for b in range(blocks):
        part = rows if blocks == 1 else rows.where(F.pmod(F.xxhash64(key, "text"), F.lit(blocks)) == b)
        yield sorted(part.collect(), key=lambda r: (r[0] is None, r[0], r[1]))


def portions(texts: list[str | None]) -> Iterator[tuple[int, list[bytes]]]:
    """Lower-case texts as bytes, some ``CHUNK`` characters at a time (one text at least), and the number of the first."""
    at = 0
    while at < len(texts):
        stop, size = at, 0
        while stop < len(texts) and (stop == at or size + len(texts[stop] or "") < CHUNK):
            size += len(texts[stop] or "")
            stop += 1
        yield at, [(t or "").lower().encode() for t in texts[at:stop]]
        at = stop


def gram_counts(docs: DataFrame, texts: list[str], text: str = "text") -> tuple[dict[int, int], int]:
    """How often each n-gram of the test items ``texts`` occurs in ``docs``, and how many n-grams these hold."""
    wanted = share(docs.sparkSession, Lookup(grams_of(words_of([t.lower().encode() for t in texts]))[0]))

    def run(batches):
        lookup = held(wanted)
        seen, total = np.zeros(len(lookup.keys), np.int64), 0
        for batch in batches:
            for _, raw in portions(batch.column(0).to_pylist()):
                gram, _ = grams_of(words_of(raw))
                seen += np.bincount(lookup.find(gram)[1], minlength=len(seen))
                total += len(gram)
        some = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array([*lookup.keys[some].view(np.int64), None]), pa.array([*seen[some], total])], names=["gram", "c"])

    # as many rows as the block has n-grams
    counts = docs.select(whole_text(text).alias("text")).mapInArrow(run, "gram long, c long").groupBy("gram").agg(F.sum("c")).collect()
    return {h % (1 << 64): c for h, c in counts if h is not None}, sum(c for h, c in counts if h is None)


def matchers(docs: DataFrame, items: DataFrame, item_key: str = "item_id", item_text: str = "text", text: str = "text", block_bytes: int = BLOCK_BYTES) -> Iterator[Matcher]:
    for rows in item_blocks(items, item_key, item_text, block_bytes):
        texts = [r[1] for r in rows]
        yield Matcher([r[0] for r in rows], texts, *(gram_counts(docs, texts, text) if texts else ()))


def passages(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row a passage of ``docs`` that copies a test item: ``key``, ``item_key``, ``score``, ``start``, ``end``."""
    kind, item_kind = docs.schema[key].dataType, items.schema[item_key].dataType
    schema = f"`{key}` {kind.simpleString()}, `{item_key}` {item_kind.simpleString()}, score double, start int, end int"
    out = docs.sparkSession.createDataFrame([], schema)
    for matcher in matchers(docs, items, item_key, item_text, text, block_bytes):
        shared = share(docs.sparkSession, matcher)

        def run(batches, shared=shared):
            m = held(shared)
            for batch in batches:
                found = m.match(batch.column(1).to_pylist())
                keys, ids = batch.column(0), pa.array(m.ids)
                cols = [keys.take(pa.array([f[0] for f in found], pa.int64())), ids.take(pa.array([f[1] for f in found], pa.int64()))]
                cols += [pa.array([f[k] for f in found], t) for k, t in ((2, pa.float64()), (3, pa.int32()), (4, pa.int32()))]
                yield pa.RecordBatch.from_arrays(cols, names=[key, item_key, "score", "start", "end"])

        out = out.union(docs.select(key, whole_text(text).alias("text")).mapInArrow(run, schema))
    return out


def _best(shared):
    @F.pandas_udf("double")
    def best(text: pd.Series) -> pd.Series:
        out = np.zeros(len(text))
        for t, _, score, _, _ in held(shared).match(text.tolist()):
            out[t] = max(out[t], score)
        return pd.Series(out)

    return best


def leak_score(docs: DataFrame, items: DataFrame, name: str, text: str = "text", item_key: str = "item_id", item_text: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``docs`` with a column ``name``: the best score of a passage of the row (0 without one). Nothing is shuffled."""
    columns = [_best(share(docs.sparkSession, m))(whole_text(text)) for m in matchers(docs, items, item_key, item_text, text, block_bytes)]
    return docs.withColumn(name, columns[0] if len(columns) == 1 else F.greatest(*columns))


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passages of all documents that copy a benchmark item, exactly or edited."""
    return passages(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
