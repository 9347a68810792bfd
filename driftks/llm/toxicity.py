"""Toxicity scores from a bidirectional gated recurrent network with attention pooling.

A word enters the network as two vectors: an embedding of the word (hashed) and the scaled sum of the
embeddings of its character 3- and 4-grams (hashed, with word ends). Two gated recurrent
layers read a window of 32 words from either side, attention pools their states, and a logistic
unit scores the window. Windows overlap by 8 words and cover the whole text; a text's score is
that of its worst window. The network is trained in numpy (Adam, manual gradients) on labelled
texts: of the windows that a step
looks at (those that were worst before and some by chance), the worst carries the text's label, and in clean texts the second
worst too.

Training reads a bounded sample of the labelled rows, ``fit_rows`` (2,400 by default), half of them of
each label where there are as many, picked by a hash of the id; labels, lang, source and ids are
never inputs. Scoring covers all rows and whole texts, and the model is broadcast (its size is
fixed by the hash buckets).

Edge cases: a null or empty text, or one without words, is one window of padding and gets that
window's score; with no labelled row, or labels of one kind only, every score is 0 or 1
accordingly (0 without any); repeated labels of an id count as toxic if one of them is; repeated
rows get equal scores; long texts take memory for their own words only; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.tables import table, whole_text
from driftks.plans.shipping import held, share

WINDOW, STRIDE = 32, 24
WORD_BUCKETS, CHAR_BUCKETS = 1 << 13, 1 << 14
WORD_DIM, CHAR_DIM, HIDDEN, ATTEND = 8, 12, 8, 8
#: Words whose network inputs one worker remembers before it starts anew.
MEMORY = 200_000
FIT_ROWS = 2400
THRESHOLD = 0.7

word_pattern = re.compile(r"\w+")


def features(word: str) -> tuple[int, list[int]]:
    """The word's bucket and the buckets of its character 3- and 4-grams; bucket 0 of either kind is padding."""
    marked = f"<{word[:64]}>" if len(word) <= 64 else f"<{word}>"
    grams = [marked[i : i + n] for n in (3, 4) for i in range(len(marked) - n + 1)]
    return 1 + zlib.crc32(word.encode()) % (WORD_BUCKETS - 1), [1 + zlib.crc32(g.encode()) % (CHAR_BUCKETS - 1) for g in grams]


def bucket_lists(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word buckets, the n-gram buckets of all words in a row, and their number for each word."""
    feats = [features(w) for w in words]
    lens = np.array([len(f[1]) for f in feats], np.int64)
    return np.array([f[0] for f in feats], np.int64), np.fromiter((g for f in feats for g in f[1]), np.int64, int(lens.sum())), lens


def window_starts(n: int) -> np.ndarray:
    """Starts of the windows over ``n`` words: every ``STRIDE`` words, the last ending with the text."""
    last = max(0, n - WINDOW)
    return np.append(np.arange(0, last, STRIDE), last)


def windows(ids: np.ndarray) -> np.ndarray:
    """Rows of ``WINDOW`` ids each, padded by 0."""
    if len(ids) < WINDOW:
        return np.pad(ids, (0, WINDOW - len(ids)))[None]
    return ids[window_starts(len(ids))[:, None] + np.arange(WINDOW)]


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (np.tanh(0.5 * x) + 1)


def _added_up(index: np.ndarray, rows: np.ndarray, size: int) -> np.ndarray:
    """``rows`` summed by ``index`` into ``size`` rows."""
    return np.stack([np.bincount(index, c, size) for c in rows.T], 1).astype(np.float32)


def _looked_at(latest: np.ndarray, r: np.random.Generator, top: int = 4, more: int = 5) -> np.ndarray:
    """The windows of a text that a training step scores: the worst when last scored, and some by chance."""
    if len(latest) <= top + more:
        return np.arange(len(latest))
    return np.unique(np.append(np.argpartition(-latest, top)[:top], r.integers(0, len(latest), more)))


class Network:
    """Weights, scoring and training."""

    def __init__(self, seed: int = 6):
        r = np.random.default_rng(seed)
        size, h = WORD_DIM + CHAR_DIM, HIDDEN
        draw = lambda *s: (r.normal(size=s) / np.sqrt(s[0])).astype(np.float32)
        self.w = {
            "word": (r.normal(size=(WORD_BUCKETS, WORD_DIM)) * 0.1).astype(np.float32),
            "char": (r.normal(size=(CHAR_BUCKETS, CHAR_DIM)) * 0.1).astype(np.float32),
            **{f"in{d}": draw(size, 3 * h) for d in (0, 1)}, **{f"bias{d}": np.zeros(3 * h, np.float32) for d in (0, 1)}, **{f"rec{d}": draw(h, 3 * h) for d in (0, 1)},
            "attend": draw(2 * h, ATTEND), "query": draw(ATTEND), "out": draw(2 * h), "base": np.zeros(1, np.float32),
        }
        self.w["word"][0] = self.w["char"][0] = 0
        self.constant: float | None = None

    def inputs(self, words: list[str]) -> np.ndarray:
        """The input vectors of distinct words."""
        return self.embedded(*bucket_lists(words))[0]

    def embedded(self, rows: np.ndarray, flat: np.ndarray, lens: np.ndarray) -> tuple[np.ndarray, tuple]:
        """The input vectors of words given by their buckets, and which rows of the embeddings they come from."""
        owner = np.repeat(np.arange(len(rows)), lens)
        scale = (1 / np.sqrt(np.maximum(lens, 1))).astype(np.float32)
        chars = np.zeros((len(rows), CHAR_DIM), np.float32)
        if len(flat):
            starts = np.cumsum(lens) - lens
            chars[lens > 0] = np.add.reduceat(self.w["char"][flat], starts[lens > 0], axis=0)
        return np.hstack([self.w["word"][rows], chars * scale[:, None]]), (rows, flat, owner, scale)

    def projected(self, x: np.ndarray) -> np.ndarray:
        """What the recurrent layers take from an input: 3 gates for each direction."""
        return np.hstack([x @ self.w["in0"] + self.w["bias0"], x @ self.w["in1"] + self.w["bias1"]])

    def logits(self, p: np.ndarray, ids: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Logits of windows; ``p``: projected inputs by word id. ``keep`` gets what the gradients need."""
        n, h, steps = len(ids), HIDDEN, ids.shape[1]
        states = np.empty((steps, n, 2 * h), np.float32)
        for d in (0, 1):
            rec, state = self.w[f"rec{d}"], np.zeros((n, h), np.float32)
            for t in range(steps) if d == 0 else range(steps - 1, -1, -1):
                x = p[ids[:, t], 3 * h * d : 3 * h * (d + 1)]
                y = state @ rec
                gates = _sigmoid(x[:, : 2 * h] + y[:, : 2 * h])
                z, r = gates[:, :h], gates[:, h:]
                c = np.tanh(x[:, 2 * h :] + r * y[:, 2 * h :])
                if keep is not None:
                    keep[d, t] = state, z, r, c, y[:, 2 * h :]
                state = state + z * (c - state)
                states[t, :, h * d : h * (d + 1)] = state
        hidden = np.tanh(states @ self.w["attend"])
        weight = hidden @ self.w["query"]
        weight = np.exp(weight - weight.max(0))
        weight /= weight.sum(0)
        pooled = np.einsum("tn,tnk->nk", weight, states)
        if keep is not None:
            keep["pool"] = states, hidden, weight, pooled
        return pooled @ self.w["out"] + self.w["base"]

    def gradients(self, x: np.ndarray, source: tuple, ids: np.ndarray, target: np.ndarray) -> dict:
        """Gradients of the mean logistic loss of windows ``ids`` over words with inputs ``x``."""
        w, h, keep = self.w, HIDDEN, {}
        logit = self.logits(self.projected(x), ids, keep)
        states, hidden, weight, pooled = keep["pool"]
        slope = ((_sigmoid(logit) - target) / len(target)).astype(np.float32)
        g = {"out": pooled.T @ slope, "base": slope.sum(keepdims=True)}
        d_pool = slope[:, None] * w["out"]
        d_weight = np.einsum("nk,tnk->tn", d_pool, states)
        d_score = weight * (d_weight - (weight * d_weight).sum(0))
        d_hidden = d_score[..., None] * w["query"] * (1 - hidden**2)
        g["query"] = np.einsum("tn,tna->a", d_score, hidden)
        g["attend"] = np.einsum("tnk,tna->ka", states, d_hidden)
        d_states = weight[..., None] * d_pool + d_hidden @ w["attend"].T
        d_x = np.zeros_like(x)
        for d in (0, 1):
            rec, into = w[f"rec{d}"], w[f"in{d}"]
            g_rec, into_all = np.zeros_like(rec), np.empty((ids.shape[1], len(ids), 3 * h), np.float32)
            later = np.zeros((ids.shape[0], h), np.float32)
            order = range(ids.shape[1]) if d == 0 else range(ids.shape[1] - 1, -1, -1)
            for t in reversed(order):
                state, z, r, c, y = keep[d, t]
                now = later + d_states[t, :, h * d : h * (d + 1)]
                d_c = now * z * (1 - c**2)
                d_z = now * (c - state) * z * (1 - z)
                d_r = d_c * y * r * (1 - r)
                into_x = into_all[t]
                into_x[:, :h], into_x[:, h : 2 * h], into_x[:, 2 * h :] = d_z, d_r, d_c
                into_y = into_x.copy()
                into_y[:, 2 * h :] *= r
                g_rec += state.T @ into_y
                later = now * (1 - z) + into_y @ rec.T
            d_p = _added_up(ids.T.ravel(), into_all.reshape(-1, 3 * h), len(x))
            g[f"rec{d}"], g[f"in{d}"], g[f"bias{d}"] = g_rec, x.T @ d_p, d_p.sum(0)
            d_x += d_p @ into.T
        rows, flat, owner, scale = source
        g["word"] = _added_up(rows, d_x[:, :WORD_DIM], WORD_BUCKETS)
        g["char"] = _added_up(flat, (d_x[:, WORD_DIM:] * scale[:, None])[owner], CHAR_BUCKETS)
        g["word"][0] = g["char"][0] = 0
        return g

    def fit(self, texts: list[str], labels: list[int], steps: int = 500, least_epochs: int = 10, batch: int = 48, rate: float = 0.006, seed: int = 16) -> Network:
        """Train on whole texts, for ``least_epochs`` and ``steps`` batches at least."""
        target = np.array(labels, np.float32)
        if not len(target) or target.min() == target.max():
            self.constant = float(target.max()) if len(target) else 0.0
            return self
        r = np.random.default_rng(seed)
        number: dict[str, int] = {"": 0}
        docs = [windows(np.array([number.setdefault(w, len(number)) for w in word_pattern.findall(t.lower())], np.int64)) for t in texts]
        word_row, gram_row, gram_count = bucket_lists(list(number))
        gram_start = np.cumsum(gram_count) - gram_count
        mean = {k: np.zeros_like(v) for k, v in self.w.items()}
        square = {k: np.zeros_like(v) for k, v in self.w.items()}
        latest = [r.normal(size=len(d)) for d in docs]
        batches = -(-len(docs) // batch)
        epochs = max(least_epochs, -(-steps // batches))
        step, total = 0, epochs * batches
        for _ in range(epochs):
            order = r.permutation(len(docs))
            for at in range(0, len(order), batch):
                some = order[at : at + batch]
                looked = [_looked_at(latest[i], r) for i in some]
                ids = np.vstack([docs[i][k] for i, k in zip(some, looked, strict=True)])
                owner = np.repeat(np.arange(len(some)), [len(k) for k in looked])
                used, local = np.unique(ids, return_inverse=True)
                local = local.reshape(ids.shape)
                lens = gram_count[used]
                flat = gram_row[np.repeat(gram_start[used] - np.cumsum(lens) + lens, lens) + np.arange(lens.sum())]
                x, source = self.embedded(word_row[used], flat, lens)
                pad = used == 0
                x[pad] = 0
                logit = self.logits(self.projected(x), local)
                for n, (i, k) in enumerate(zip(some, looked, strict=True)):
                    latest[i][k] = logit[owner == n]
                rank = np.lexsort((-logit, owner))
                first = np.searchsorted(owner[rank], np.arange(len(some)))
                second = np.minimum(first + 1, len(rank) - 1)
                # a clean text is clean in its second worst window too; a toxic one may be toxic in one window only
                too = (owner[rank[second]] == np.arange(len(some))) & (target[some] == 0)
                both = np.concatenate([rank[first], rank[second[too]]])
                g = self.gradients(x, source, local[both], target[some][owner[both]])
                step += 1
                speed = rate * (1 - 0.9 * step / total) * np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
                for k, v in g.items():
                    mean[k] += 0.1 * (v - mean[k])
                    square[k] += 0.001 * (v * v - square[k])
                    self.w[k] -= (speed * mean[k] / (np.sqrt(square[k]) + 1e-7)).astype(np.float32)
        return self


class Scorer:
    """Scores texts with a trained network; remembers the projected inputs of words."""

    def __init__(self, net: Network):
        self.net = net
        self.reset()

    def reset(self) -> None:
        self.number: dict[str, int] = {}
        self.rows = self.net.projected(np.zeros((1, WORD_DIM + CHAR_DIM), np.float32))

    def ids(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.number) > MEMORY:
            self.reset()
        number, new, out = self.number, [], []
        for text in texts:
            words = word_pattern.findall(text.lower())
            try:
                out.append(np.fromiter(map(number.__getitem__, words), np.int32, len(words)))
            except KeyError:
                for w in words:
                    if w not in number:
                        number[w] = len(number) + 1
                        new.append(w)
                out.append(np.fromiter(map(number.__getitem__, words), np.int32, len(words)))
        if new:
            self.rows = np.vstack([self.rows, self.net.projected(self.net.inputs(new))])
        return out

    def scores(self, texts: list[str], block: int = 4096) -> np.ndarray:
        if self.net.constant is not None:
            return np.full(len(texts), self.net.constant)
        each = [windows(i) for i in self.ids(texts)]
        ids = np.vstack(each)
        logit = np.concatenate([self.net.logits(self.rows, ids[i : i + block]) for i in range(0, len(ids), block)])
        starts = np.cumsum([0, *map(len, each[:-1])])
        return _sigmoid(np.maximum.reduceat(logit, starts)).astype(np.float64)


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, key: str = "doc_id", text: str = "text", label: str = "toxic") -> Network:
    """Train on at most ``fit_rows`` labelled rows of ``docs``. The sample is drawn from ids and labels
    alone; only its ids (a bounded set) are broadcast to fetch their texts."""
    known = labels.where(F.col(label).isNotNull() & F.col(key).isNotNull()).groupBy(key).agg(F.max(F.col(label).cast("int")).alias("y"))
    known = known.join(docs.where(F.col(text).isNotNull()).select(key).distinct(), key, "left_semi")
    order = F.xxhash64(F.lit(6), F.col(key))
    half = fit_rows // 2
    toxic = known.where("y > 0").orderBy(order).limit(half)
    clean = known.where("y <= 0").orderBy(order).limit(half)
    some = toxic.union(clean).collect()
    if not some:
        return Network().fit([], [])
    picked = F.broadcast(docs.sparkSession.createDataFrame(some, known.schema))
    rows = docs.select(key, text).join(picked, key).where(F.col(text).isNotNull()).dropDuplicates([key]).select(key, text, "y").collect()
    rows.sort(key=lambda r: r[0])
    return Network().fit([r[1] for r in rows], [int(r[2] > 0) for r in rows])


def score(df: DataFrame, net: Network, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key`` and ``score`` of every row; other columns named in ``df`` go with it as they are."""
    return df.withColumn("score", scorer(df.sparkSession, net)(whole_text(text)))


def scorer(spark: SparkSession, net: Network):
    """A vectorised function from text to score."""
    shared = share(spark, Scorer(net))

    @F.pandas_udf("double")
    def toxic(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = held(shared)
        for batch in batches:
            texts, out, at = batch.tolist(), [], 0
            while at < len(texts):  # some 2 MB at a time, one text at least
                end, size = at, 0
                while end < len(texts) and (end == at or size + len(texts[end]) < 2_000_000):
                    size += len(texts[end])
                    end += 1
                out.append(model.scores(texts[at:end]))
                at = end
            yield pd.Series(np.concatenate(out) if out else np.zeros(0))

    return toxic


def held_out(key: str = "doc_id"):
    """Whether a row's label is never learned from."""
    return F.pmod(F.crc32(F.encode(F.coalesce(F.col(key).cast("string"), F.lit("")), "UTF-8")), F.lit(3)) == 1


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scored; labels of held-out rows are not read."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    net = fit(docs, labels.where(~held_out()))
    scored = score(docs.select("doc_id", "text"), net)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
