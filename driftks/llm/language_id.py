"""Language of texts and of the spans of mixed texts.

A word's script (ranges of code points) narrows the languages that can be meant to those that wrote
in it when the model was fitted. Among them, a word scores by its character n-grams under a
naive Bayes model. A Viterbi path over the words, which pays a penalty for each change of
language, labels every word; neighbouring words with one label make a span. A text's language is the
one with most letters on the path, and its score is the share of those letters times the posterior
of that language over the whole text.

The model is fitted on a bounded sample of labelled texts, at most ``per_lang`` of each language, picked
by a hash of id and text; every value of the label is learned. Tasks count the n-grams of the
sample, so the driver gets counts (bounded by the model's size) and no texts. The n-gram
table has fewer buckets where there are very many languages, so that it stays within ``CELLS`` numbers.
Labels, source and id are never inputs of a prediction. Predictions read whole texts; all paths
of a batch are computed together, one word of every text at a time. The path of a very long text
is worked out in stretches of ``STRETCH`` words, forward once to the begin of each and then, from the last to
the first, once more with its back-pointers, so memory holds one stretch.

Words and spans have the places of the text itself: it is cut into words first and each is
lower-cased by itself.

Edge cases: a null text, or one without a letter, is ``und`` with score 0; so is every text if nothing
was learned; a word in a script that no learned language writes can be any of them; repeated rows
get equal results; ties go to the language that sorts first; a text of any length is one path; other
columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftks.llm.tables import table, whole_text
from driftks.plans.shipping import held, share

BUCKETS, CELLS = 1 << 17, 1 << 26
PER_LANG = 700
STRETCH = 200_000
#: What one word can say against a language at most, and what a change of language costs: more, so one word makes no span.
MOST, PENALTY = 6.0, 8.0
#: Words whose scores a worker remembers before it starts anew, and numbers that these take at most.
MEMORY, MEMORY_CELLS = 300_000, 20_000_000
GRAMS = 200_000  # n-grams whose buckets a worker remembers
UNKNOWN = "und"

# First and last code points of the scripts that are told apart.
SCRIPTS = {
    "latin": [(0x41, 0x5A), (0x61, 0x7A), (0xAA, 0xAA), (0xBA, 0xBA), (0xC0, 0x24F), (0x1E00, 0x1EFF)],
    "greek": [(0x370, 0x3FF), (0x1F00, 0x1FFF)],
    "cyrillic": [(0x400, 0x52F), (0x1C80, 0x1C8F)],
    "armenian": [(0x531, 0x58F)],
    "hebrew": [(0x591, 0x5F4)],
    "arabic": [(0x600, 0x6FF), (0x750, 0x77F), (0x8A0, 0x8FF)],
    "devanagari": [(0x900, 0x97F)],
    "bengali": [(0x980, 0x9FF)],
    "gurmukhi": [(0xA00, 0xA7F)],
    "gujarati": [(0xA80, 0xAFF)],
    "tamil": [(0xB80, 0xBFF)],
    "telugu": [(0xC00, 0xC7F)],
    "kannada": [(0xC80, 0xCFF)],
    "malayalam": [(0xD00, 0xD7F)],
    "sinhala": [(0xD80, 0xDFF)],
    "thai": [(0xE00, 0xE7F)],
    "lao": [(0xE80, 0xEFF)],
    "georgian": [(0x10A0, 0x10FF), (0x1C90, 0x1CBF)],
    "ethiopic": [(0x1200, 0x139F)],
    "khmer": [(0x1780, 0x17FF)],
    "kana": [(0x3040, 0x30FF), (0x31F0, 0x31FF)],
    "han": [(0x3400, 0x4DBF), (0x4E00, 0x9FFF), (0x20000, 0x2FA1F)],
    "hangul": [(0x1100, 0x11FF), (0xAC00, 0xD7A3)],
}
word_pattern = re.compile(r"[^\W\d_]+")


def script(word: str) -> str:
    """The script of a word's first letter (``other`` outside the ranges)."""
    code = next((ord(c) for c in word if c.isalpha()), 0)
    return next((name for name, ranges in SCRIPTS.items() if any(a <= code <= b for a, b in ranges)), "other")


class Buckets(dict):
    """The buckets of n-grams that were seen, ``GRAMS`` at most: few n-grams make most of the words."""

    def __init__(self, size: int):
        self.size = size

    def __missing__(self, gram: str) -> int:
        if len(self) >= GRAMS:
            self.clear()
        at = self[gram] = zlib.crc32(gram.encode()) % self.size
        return at


_buckets: dict[int, Buckets] = {}


def grams(word: str, buckets: int = BUCKETS) -> list[int]:
    """Buckets of the word's 1- to 4-grams with word ends, and of the whole word."""
    if buckets not in _buckets:
        _buckets[buckets] = Buckets(buckets)
    of, marked = _buckets[buckets], f"<{word}>"
    return [of[marked[i : i + n]] for n in (1, 2, 3, 4) for i in range(len(marked) - n + 1)] + [zlib.crc32(word.encode(), 1) % buckets]


def buckets_for(langs: int) -> int:
    """Buckets of the n-gram table for so many languages."""
    size = BUCKETS
    while size > 1024 and size * langs > CELLS:
        size //= 2
    return size


class Model:
    """Log-probabilities of n-grams by language, and the languages of each script."""

    def __init__(self, langs: list[str], counts: np.ndarray, letters: dict[str, np.ndarray]):
        """``counts``: of n-grams by bucket and language; ``letters``: of each script by language."""
        self.langs, self.buckets = langs, len(counts)
        self.logp = np.log((counts + 0.2) / (counts.sum(0) + 0.2 * self.buckets)).astype(np.float32) if langs else counts
        share = {s: v / np.maximum(sum(letters.values()), 1) for s, v in letters.items()}
        self.writes = {s: v >= 0.01 for s, v in share.items() if (v >= 0.01).any()}

    def scores(self, words: list[str]) -> np.ndarray:
        """Scores of distinct words by language, 0 for the best one."""
        feats = [grams(w, self.buckets) for w in words]
        lens = np.array([len(f) for f in feats])
        total = np.add.reduceat(self.logp[np.fromiter((g for f in feats for g in f), np.int64, int(lens.sum()))], np.cumsum(lens) - lens, axis=0)
        everyone = np.ones(len(self.langs), bool)
        total[~np.array([self.writes.get(script(w), everyone) for w in words])] = -1e9
        return np.maximum(total - total.max(1, keepdims=True), -MOST)


def paths(scores: np.ndarray, lens: np.ndarray, penalty: float = PENALTY) -> np.ndarray:
    """Best label of every word of texts that follow each other in ``scores``; ``lens``: their words.

    All texts advance together by one word, the longest first, so a step is a few array operations.
    """
    n = scores.shape[1]
    labels = np.zeros(len(scores), np.int16)
    order = np.argsort(-lens, kind="stable")
    lens, starts = lens[order], (np.cumsum(lens) - lens)[order]
    if not len(lens) or not lens[0]:
        return labels
    active = np.searchsorted(-lens, -np.arange(lens[0]), side="left")  # texts with more than t words
    came = np.zeros((len(scores), n), np.int16)
    own = np.arange(n, dtype=np.int16)
    best = scores[starts[: active[0]]].astype(np.float32)
    for t in range(1, lens[0]):
        a = active[t]
        best = best[:a] if t == 1 or a < len(best) else best
        top = best.argmax(1)
        jump = best[np.arange(a), top][:, None] - penalty
        at = starts[:a] + t
        came[at] = np.where(best >= jump, own, top[:, None])
        new = np.maximum(best, jump) + scores[at]
        if t + 1 < lens[0] and active[t + 1] < a or t + 1 == lens[0]:
            ended = active[t + 1] if t + 1 < lens[0] else 0
            labels[at[ended:]] = new[ended:].argmax(1)
        best = new
    ended = active[1] if lens[0] > 1 else 0
    first = starts[ended : active[0]]
    labels[first] = scores[first].argmax(1)
    for t in range(lens[0] - 1, 0, -1):
        at = starts[: active[t]] + t
        labels[at - 1] = came[at, labels[at]]
    return labels


def long_path(rows: np.ndarray, ids: np.ndarray, penalty: float = PENALTY, stretch: int = STRETCH) -> np.ndarray:
    """Best label of every word of one text (``rows``: scores by word number), one stretch of back-pointers in memory."""
    n, own = rows.shape[1], np.arange(rows.shape[1], dtype=np.int16)

    def forward(best: np.ndarray, words: np.ndarray, came: np.ndarray | None) -> np.ndarray:
        for t, w in enumerate(words):
            top = int(best.argmax())
            jump = best[top] - penalty
            if came is not None:
                came[t] = np.where(best >= jump, own, top)
            best = np.maximum(best, jump) + rows[w]
            best -= best.max()  # the differences decide, and sums of millions of words would lose them
        return best

    begins = list(range(1, len(ids), stretch))
    at = [rows[ids[0]].astype(np.float32)]
    for b in begins[:-1]:
        at.append(forward(at[-1], ids[b : b + stretch], None))
    labels = np.zeros(len(ids), np.int16)
    for k in range(len(begins) - 1, -1, -1):
        words = ids[begins[k] : begins[k] + stretch]
        came = np.empty((len(words), n), np.int16)
        last = forward(at[k], words, came)
        if k == len(begins) - 1:
            labels[-1] = last.argmax()
        for t in range(len(words) - 1, -1, -1):
            labels[begins[k] + t - 1] = came[t, labels[begins[k] + t]]
    if not begins:
        labels[0] = at[0].argmax()
    return labels


class Labeller:
    """Applies a model; remembers the scores and letters of words."""

    def __init__(self, model: Model):
        self.model = model
        self.reset()

    def reset(self) -> None:
        self.number: dict[str, int] = {}
        self.rows = np.zeros((0, len(self.model.langs)), np.float32)
        self.letters = np.zeros(0, np.int64)

    def ids(self, texts: list[list[str]]) -> list[np.ndarray]:
        if len(self.number) > min(MEMORY, MEMORY_CELLS // max(1, len(self.model.langs))):
            self.reset()
        number, new, out = self.number, [], []
        for words in texts:
            try:
                out.append(np.fromiter(map(number.__getitem__, words), np.int32, len(words)))
            except KeyError:
                for w in words:
                    if w not in number:
                        number[w] = len(number)
                        new.append(w)
                out.append(np.fromiter(map(number.__getitem__, words), np.int32, len(words)))
        if new:
            self.rows = np.vstack([self.rows, self.model.scores([w.lower() for w in new])])
            self.letters = np.append(self.letters, [sum(map(str.isalpha, w)) for w in new])
        return out

    def label(self, texts: list[str], spans: bool = False):
        """For each text: language, score and, on request, (start, end, language) runs."""
        langs = self.model.langs
        if not langs:
            return [(UNKNOWN, 0.0, [])] * len(texts)
        words = [word_pattern.findall(t) for t in texts]
        ids = self.ids(words)
        lens = np.array(list(map(len, ids)))
        flat = np.concatenate(ids) if len(ids) else np.zeros(0, np.int32)
        letters, n = self.letters[flat], len(langs)
        total, some = np.zeros((len(texts), n)), lens > 0
        if len(texts) == 1 and lens[0] > STRETCH:
            labels = long_path(self.rows, flat)
            for at in range(0, len(flat), STRETCH):
                part = flat[at : at + STRETCH]
                total[0] += (self.rows[part] * (self.letters[part] > 0)[:, None]).sum(0, dtype=float)
        else:
            scores = self.rows[flat]
            labels = paths(scores, lens)
            if some.any():
                total[some] = np.add.reduceat(scores * (letters > 0)[:, None], (np.cumsum(lens) - lens)[some], axis=0, dtype=float)
        owner = np.repeat(np.arange(len(texts)), lens)
        won = np.bincount(owner * n + labels, letters, len(texts) * n).reshape(len(texts), n)
        pick = won.argmax(1)
        at = np.arange(len(texts))
        sure = 1 / np.exp(np.minimum(total - total[at, pick][:, None], 50)).sum(1)
        all_letters = won.sum(1)
        score = np.where(all_letters > 0, won[at, pick] / np.maximum(all_letters, 1) * sure, 0.0)
        ends = np.cumsum(lens)
        out = []
        for k, text in enumerate(texts):
            runs = _runs(text, words[k], labels[ends[k] - lens[k] : ends[k]], langs) if spans and all_letters[k] else []
            out.append((langs[pick[k]] if all_letters[k] else UNKNOWN, float(score[k]), runs))
        return out


def _runs(text: str, words: list[str], labels: np.ndarray, langs: list[str]) -> list[tuple[int, int, str]]:
    """Neighbouring words with one label, by their places in the text."""
    change = np.flatnonzero(labels[1:] != labels[:-1])
    first, last = word_pattern.search(text).start(), text.rfind(words[-1]) + len(words[-1])
    if not len(change):
        return [(first, last, langs[labels[0]])]
    places = [m.span() for m in word_pattern.finditer(text)]
    starts = [first, *(places[i + 1][0] for i in change)]
    ends = [*(places[i][1] for i in change), last]
    return [(a, z, langs[labels[i]]) for a, z, i in zip(starts, ends, [0, *(change + 1)], strict=True)]


def fit(docs: DataFrame, per_lang: int = PER_LANG, key: str = "doc_id", text: str = "text", lang: str = "lang") -> Model:
    """Fit on at most ``per_lang`` rows of each label of ``docs``: those with the least hashes of id and text."""
    spark = docs.sparkSession
    known = docs.where(F.col(lang).isNotNull() & F.col(text).isNotNull())
    counts = known.groupBy(lang).count().collect()  # a row a language
    if not counts:
        return Model([], np.zeros((0, 0)), {})
    langs = sorted(r[0] for r in counts)
    buckets = buckets_for(len(langs))
    share = spark.createDataFrame([(r[0], langs.index(r[0]), min(1.0, 2 * per_lang / r[1])) for r in counts], "__lang string, __no int, __share double")
    mixed = F.xxhash64(F.lit(4), F.col(key), F.col(text))
    drawn = F.pmod(F.xxhash64(F.lit(4), F.col(key)), F.lit(1 << 30)) < F.col("__share") * (1 << 30)
    met = known.join(F.broadcast(share), F.col(lang) == F.col("__lang")).where(drawn).select("__no", F.col(text).alias("__text"), mixed.alias("__mixed"))
    rank = F.row_number().over(Window.partitionBy("__no").orderBy("__mixed"))
    rows = met.withColumn("__rank", rank).where(F.col("__rank") <= per_lang).select("__no", "__text")
    scripts = [*SCRIPTS, "other"]

    def count(batches):
        grammed: Counter = Counter()
        for batch in batches:
            for no, body in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for word, c in Counter(map(str.lower, word_pattern.findall(body))).items():
                    for g in grams(word, buckets):
                        grammed[no, g] += c
                    grammed[no, buckets + scripts.index(script(word))] += c * len(word)
        if grammed:
            nos, places = zip(*grammed, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(nos, pa.int32()), pa.array(places, pa.int32()), pa.array(list(grammed.values()), pa.int64())], names=["no", "place", "c"])

    found = rows.mapInArrow(count, "no int, place int, c long").groupBy("no", "place").agg(F.sum("c").alias("c")).toArrow()
    table_ = np.zeros((buckets + len(scripts), len(langs)))
    table_[found["place"].to_numpy(), found["no"].to_numpy()] = found["c"].to_numpy()
    learned = np.flatnonzero(table_.any(0))
    table_ = table_[:, learned]
    letters = {s: table_[buckets + i] for i, s in enumerate(scripts) if table_[buckets + i].any()}
    return Model([langs[i] for i in learned], table_[:buckets], letters)


def identify(df: DataFrame, model: Model, key: str = "doc_id", text: str = "text", spans: bool = False) -> DataFrame:
    """``key``, ``lang_pred``, ``score`` and, on request, ``spans`` of every row."""
    shared = share(df.sparkSession, Labeller(model))
    kind = df.schema[key].dataType

    def run(batches):
        labeller = held(shared)
        for batch in batches:
            texts, at = batch.column(1).to_pylist(), 0
            while at < len(texts):  # some 6 MB at a time, one text at least
                end, size = at, 0
                while end < len(texts) and (end == at or size + len(texts[end]) < 6_000_000):
                    size += len(texts[end])
                    end += 1
                found = labeller.label(texts[at:end], spans)
                cols = [batch.column(0).slice(at, end - at), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())]
                names = [key, "lang_pred", "score"]
                if spans:
                    item = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("lang", pa.string())])
                    cols.append(pa.array([[dict(start=a, end=b, lang=c) for a, b, c in f[2]] for f in found], pa.list_(item)))
                    names.append("spans")
                yield pa.RecordBatch.from_arrays(cols, names=names)
                at = end

    schema = f"`{key}` {kind.simpleString()}, lang_pred string, score double" + ", spans array<struct<start:int,end:int,lang:string>>" * spans
    return df.select(key, whole_text(text).alias("text")).mapInArrow(run, schema)


def held_out(key: str = "doc_id") -> Column:
    """Whether a row's label is never learned from."""
    return F.pmod(F.crc32(F.encode(F.coalesce(F.col(key).cast("string"), F.lit("")), "UTF-8")), F.lit(4)) == 2


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document, and its spans (start:end:language); labels of held-out rows are not read."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = fit(docs.where(~held_out()))
    said = identify(docs.select("doc_id", "text"), model, spans=True)
    spans = F.array_join(F.transform("spans", lambda x: F.concat_ws(":", x["start"], x["end"], x["lang"])), ",")
    return said.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", spans.alias("spans"))
