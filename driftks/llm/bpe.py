"""Byte-pair encoding by a tokenization automaton.

The merges are compiled, one gadget after the other, into a deterministic automaton
whose arcs carry tokens. It begins as one state that loops on every base symbol. The
gadget of a merge ``u v -> w`` looks at the state that ``u`` leads to: if ``v`` can
follow there, ``u`` from now on leads to a copy of that state without the arc ``v``, and
wherever ``u`` can be read, ``w`` can be read too and leads to where ``v`` led. Two facts
keep the automaton small. A token leads to one state from everywhere, and a state differs
from the one it was copied from by one missing arc, so a state is a (parent, missing arc,
time) triple and 48,894 merges give as many states at most. Which arcs leave a state follows
from those triples: the table keeps, for each token, the states that lack its arc as ranges of
a depth-first numbering of the copies (as a full table of states by tokens it would have 2.4 thousand million
entries).

The words are read symbol by symbol through a second table, compiled from the labels of all
arcs: a state of it is the longest end of what was read that begins a label, with its move on
every symbol (or the state that it falls back to), and names the labels that end here, longest
first. Exactly one path of the merge automaton spells any word; at each symbol, the one label that
ends there and whose arc leaves the state where it begins goes on. Decoding emits the labels of the
arcs.

The pre-split (NFC, per-character lower case, a fixed word pattern), the ``</w>`` mark and
the added tokens are those of the tokenizer file; the result equals that of the
``tokenizers`` library on it.

Edge cases: a null or empty text has no tokens and decodes to the empty text; repeated rows
are encoded one by one; other columns of the input are not looked at; a text of any length is
encoded whole (the work per word is bounded by the longest token).
"""

from __future__ import annotations

import json
import re
import unicodedata
from bisect import bisect_right

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.tables import table, whole_text
from driftks.plans.shipping import held, share

WORD_END = "</w>"
#: Words whose arcs a worker remembers, half of them the latest, and bytes of results that leave it at once.
MEMORY, PORTION = 800_000, 4_000_000


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class MergeAutomaton:
    """The automaton of a merge list; ``arcs(word)`` gives the tokens on the word's path."""

    def __init__(self, vocab: dict[str, int], merges: list[tuple[str, str]]):
        self.vocab, self.label = vocab, {i: t for t, i in vocab.items()}
        size = max(vocab.values(), default=-1) + 1
        # of a token: its left part, the merge that made it (-1: a base symbol), the state it leads to
        self.left, self.made, self.leads = [-1] * size, [-1] * size, [0] * size
        # of a state: the one it was copied from, the arc it lacks, the merge that made it
        self.parent, self.lacks, self.since = [-1], [-1], [-1]
        for time, (a, b) in enumerate(merges):
            self._gadget(time, vocab[a], vocab[b], vocab[a + b])
        self._index()
        self._compile()

    def _gadget(self, time: int, u: int, v: int, w: int) -> None:
        state, beyond = self.leads[u], self.leads[v]
        if not self._leaves(state, v):
            return
        self.parent.append(state)
        self.lacks.append(v)
        self.since.append(time)
        self.left[w], self.made[w], self.leads[w] = u, time, beyond
        self.leads[u] = len(self.parent) - 1

    def _leaves(self, state: int, token: int) -> bool:
        """Whether an arc for ``token`` leaves ``state``: walk back through the copies, and
        through the left parts of the token where a copy is older than the token."""
        parent, lacks, since, left, made = self.parent, self.lacks, self.since, self.left, self.made
        while state > 0:
            while made[token] >= since[state]:
                token = left[token]
            if lacks[state] == token:
                return False
            state = parent[state]
        return True

    def _index(self) -> None:
        """Number the tree of copies in depth-first order. The states below one that lacks a
        token are then a range, and those ranges are disjoint for one token, since no state
        loses an arc twice: whether a state lacks a token is one bisection."""
        below: list[list[int]] = [[] for _ in self.parent]
        for state in range(1, len(self.parent)):
            below[self.parent[state]].append(state)
        self.first, self.past, clock, todo = [0] * len(below), [0] * len(below), 0, [(0, False)]
        while todo:
            state, over = todo.pop()
            if over:
                self.past[state] = clock
                continue
            self.first[state] = clock
            clock += 1
            todo.append((state, True))
            todo += [(s, False) for s in below[state]]
        cuts: dict[int, list[tuple[int, int, int]]] = {}
        for state in range(1, len(self.parent)):
            cuts.setdefault(self.lacks[state], []).append((self.first[state], self.past[state], self.since[state]))
        self.cuts = {t: tuple(zip(*sorted(c), strict=True)) for t, c in cuts.items()}

    def follows(self, state: int, token: int) -> bool:
        """As ``_leaves``, from the table: no state on the way back lacks the token, or a left
        part of it at a time when that part was not yet merged."""
        at, until = self.first[state], len(self.since) + len(self.made)
        while token >= 0:
            cut = self.cuts.get(token)
            if cut is not None:
                i = bisect_right(cut[0], at) - 1
                if i >= 0 and at < cut[1][i] and cut[2][i] <= until:
                    return False
            until, token = self.made[token], self.left[token]
        return True

    def _compile(self) -> None:
        """The symbol table: moves by (state, symbol), fall-back states, and the labels that end in each state."""
        self.symbol: dict[str, int] = {}
        self.moves: dict[int, int] = {}
        self.fall, self.ends, self.beyond, depth = [0], [-1], [0], [0]
        self.size = [0] * len(self.made)
        for label, token in self.vocab.items():
            symbols = spelled(label)
            if not symbols or len(symbols) > 1 and self.made[token] < 0:
                continue  # no arc has it: added tokens
            self.size[token] = len(symbols)
            node = 0
            for s in symbols:
                key = node << 10 | self.symbol.setdefault(s, len(self.symbol))
                if key not in self.moves:
                    self.moves[key] = len(self.fall)
                    self.fall.append(0)
                    self.ends.append(-1)
                    self.beyond.append(0)
                    depth.append(depth[node] + 1)
                node = self.moves[key]
            self.ends[node] = token
        # the shallower states are ready when a deeper one falls back to them
        for key, node in sorted(self.moves.items(), key=lambda m: depth[m[1]]):
            above, s = key >> 10, key & 1023
            back = self.fall[above]
            while above and back and (back << 10 | s) not in self.moves:
                back = self.fall[back]
            to = self.moves.get(back << 10 | s, 0) if above else 0
            self.fall[node] = to
            self.beyond[node] = to if self.ends[to] >= 0 else self.beyond[to]

    def arcs(self, symbols: str) -> list[int]:
        """Token ids of a word given as byte symbols, the last of which ends the word."""
        number, moves, fall, ends, beyond, size, leads, follows = self.symbol, self.moves, self.fall, self.ends, self.beyond, self.size, self.leads, self.follows
        n = len(symbols)
        state, last, node = [0] * (n + 1), [-1] * (n + 1), 0
        for end in range(1, n + 1):
            s = number[symbols[end - 1] + WORD_END if end == n else symbols[end - 1]]
            while (to := moves.get(node << 10 | s)) is None and node:
                node = fall[node]
            node = to or 0
            here = node if ends[node] >= 0 else beyond[node]
            while here:
                token = ends[here]
                if follows(state[end - size[token]], token):
                    state[end], last[end] = leads[token], token
                    break
                here = beyond[here]
            else:
                raise ValueError(f"no path spells {symbols!r}")
        out = []
        while n:
            out.append(last[n])
            n -= size[last[n]]
        return out[::-1]


def spelled(label: str) -> list[str]:
    """The symbols of a label: its characters, the last with the mark of a word's end if the label has it."""
    if label.endswith(WORD_END) and label != WORD_END:
        return [*label[: -len(WORD_END) - 1], label[-len(WORD_END) - 1 :]]
    return list(label)


class WordEncoder:
    """Added tokens, normalisation and pre-split of a tokenizer file in front of its automaton."""

    #: Letters and numbers below U+0250, where the standard library's matcher does.
    LETTER = "A-Za-zªµºÀ-ÖØ-öø-ɏ"
    NUMBER = "0-9²³¹¼-¾"
    SPACE = "\t-\r \u0085 "

    def __init__(self, spec: dict):
        model = spec["model"]
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.automaton = MergeAutomaton(model["vocab"], merges)
        self.added = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.label = self.automaton.label | {i: t for t, i in self.added.items()}
        self.symbols = byte_symbols()

    def ready(self, labels: bool = True, memory: int = MEMORY) -> WordEncoder:
        """Compile what isn't pickled: the matchers and the memory of ``memory`` words, whose labels are
        left out on request. A worker that is used again finds both as the task before left them."""
        if hasattr(self, "known"):
            return self
        import regex

        ends = "'s|'t|'re|'ve|'m|'ll|'d"
        self.near = re.compile(f"{ends}|[{self.LETTER}]+|[{self.NUMBER}]|[^{self.SPACE}{self.LETTER}{self.NUMBER}]+").findall
        self.far = regex.compile(rf"{ends}|\p{{L}}+|\p{{N}}|[^\p{{White_Space}}\p{{L}}\p{{N}}]+").findall
        self.beyond = re.compile("[^\x00-ɏ]").search
        self.at = re.compile("|".join(map(re.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        self.marks = {t[0] for t in self.added if t}
        self.known: dict[str, tuple[bytes, bytes]] = {}
        self.older: dict[str, tuple[bytes, bytes]] = {}
        self.labels, self.most = labels, memory // 2
        return self

    def words(self, text: str) -> list[str]:
        text = text.lower() if text.isascii() else unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()
        return (self.far if not text.isascii() and self.beyond(text) else self.near)(text)

    def pack(self, ids: list[int]) -> tuple[bytes, bytes]:
        return b"".join(i.to_bytes(4, "little") for i in ids), " ".join(self.label[i] for i in ids).encode() if self.labels else b""

    def word(self, word: str) -> tuple[bytes, bytes]:
        """A word that isn't among the latest. Those before them are kept until the latest are full once more: frequent words stay."""
        if len(self.known) >= self.most:
            self.older, self.known = self.known, {}
        self.known[word] = out = self.older.get(word) or self.pack(self.automaton.arcs("".join([self.symbols[b] for b in word.encode()])))
        return out

    def spelled(self, words: list[str]) -> list[tuple[bytes, bytes]]:
        try:
            return list(map(self.known.__getitem__, words))
        except KeyError:
            return [self.known.get(w) or self.word(w) for w in words]

    def encode(self, text: str) -> tuple[bytes, bytes]:
        """The ids as little-endian unsigned 32-bit integers, and the labels of their arcs joined by blanks."""
        parts: list[tuple[bytes, bytes]] = []
        done = 0
        for piece in self.at.finditer(text) if any(c in text for c in self.marks) else ():
            parts += self.spelled(self.words(text[done : piece.start()]))
            parts.append(self.pack([self.added[piece[0]]]))
            done = piece.end()
        parts += self.spelled(self.words(text[done:] if done else text))
        return b"".join([p[0] for p in parts]), b" ".join([p[1] for p in parts]) if self.labels else b""

    def decode(self, ids: bytes) -> str:
        """The labels of the arcs with these ids, as the library joins them without a decoder."""
        label = self.label
        return " ".join([label[i] for i in memoryview(ids).cast("I")])


def load(path: str) -> WordEncoder:
    """Compile the automaton of a tokenizer file (read on the driver; its size is that of the vocabulary)."""
    with open(path, encoding="utf-8") as f:
        return WordEncoder(json.load(f))


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode(df: DataFrame, text: str = "text", key: str = "doc_id", path: str | None = None, decode: bool = False, memory: int = MEMORY) -> DataFrame:
    """``key``, ``ids`` (binary, little-endian unsigned 32-bit), ``n_tokens`` and, on request, ``decoded``.

    The compiled automaton is broadcast: it is bounded by the vocabulary, not by the data. A worker remembers the
    arcs of ``memory`` words; with fewer it is smaller and slower, with the same results.
    """
    shared = share(df.sparkSession, load(path or default_path()))
    kind = df.schema[key].dataType
    fields = [pa.field("ids", pa.binary()), pa.field("n_tokens", pa.int64())] + [pa.field("decoded", pa.string())] * decode

    def run(batches):
        encoder = held(shared).ready(decode, memory)
        for batch in batches:
            texts, at = batch.column(1), 0
            while at < batch.num_rows:  # some ``PORTION`` bytes of results at a time, one text at least
                out, size = [], 0
                while at + len(out) < batch.num_rows and size < PORTION:
                    out.append(encoder.encode(texts[at + len(out)].as_py()))
                    size += len(out[-1][0]) + len(out[-1][1])
                cols = [batch.column(0).slice(at, len(out)), pa.array([o[0] for o in out], pa.binary()), pa.array([len(o[0]) // 4 for o in out], pa.int64())]
                if decode:
                    cols.append(pa.array([o[1] for o in out], pa.binary()).cast(pa.string()))
                at += len(out)
                yield pa.RecordBatch.from_arrays(cols, names=[key, *(f.name for f in fields)])
                pa.default_memory_pool().release_unused()

    schema = f"`{key}` {kind.simpleString()}, ids binary, n_tokens long" + ", decoded string" * decode
    return df.select(key, whole_text(text).alias("text")).mapInArrow(run, schema)


def decode(df: DataFrame, key: str = "doc_id", ids: str = "ids", path: str | None = None) -> DataFrame:
    """``key`` and ``decoded``, the text that the ids spell (null ids: the empty text)."""
    shared = share(df.sparkSession, load(path or default_path()))
    kind = df.schema[key].dataType

    def run(batches):
        encoder = held(shared)
        for batch in batches:
            texts = [encoder.decode(b or b"") for b in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=[key, "decoded"])

    return df.select(key, ids).mapInArrow(run, f"`{key}` {kind.simpleString()}, decoded string")


def op9_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded and decoded with the 49k word vocabulary."""
    out = encode(table(spark, sf_dir, "documents"), decode=True)
    return out.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.encode("decoded", "UTF-8"), 256).alias("decoded_sha256"))
