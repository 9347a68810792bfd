"""Secret scan in built-in functions only.

Three patterns give the base findings: assignments of a secret, access key ids and long lower-case
hex runs. On top of them, every run of 20 or more token characters that holds a letter and a digit
is a candidate. A window of 20 characters slides over it; its Shannon entropy over the
candidate's character class comes from counts that change by one character in and one out, and the
sum of ``c log2 c`` that changes with them. A candidate whose best window passes the class's
threshold is a finding of kind ``entropy`` unless an allow-list pattern matches it or a base
finding already covers part of it.

A span is the place of a whole match in code points, end exclusive. Built-in functions give matches
but not places; those follow from the lengths of what stands between the matches.

Edge cases: a null text is an empty one and has no span; texts of any length are scanned whole;
equal findings at different places count each; repeated rows give repeated results; other
columns are ignored, so their names cannot clash.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.tables import bound, table, whole_text

# The base patterns and the least length of what they must find.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
LEAST = {"assign": 6, "access": 20, "hex": 24}
KINDS = ("assign", "access", "hex", "entropy")

WINDOW = 20
TOKEN = r"[A-Za-z0-9+/_=-]{20,}"
#: Character class -> its characters and the bits per character from which a window counts.
CLASSES = {"hex": ("0123456789abcdef", 3.0), "token": ("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-", 3.9)}
#: Candidates that are no secrets: UUIDs, digests with their algorithm's name, placeholders, counting rows and paths of words.
ALLOW = (
    r"^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$",
    r"(?i)^(md5|sha1|sha256|sha384|sha512)[-_=]",
    r"(?i)example|placeholder|changeme|dummy|x{6}",
    r"(?i)0123456789|abcdefghij",
    r"^/?[a-z0-9_-]{1,14}(/[a-z0-9_-]{1,14}){2,}/?$",
)

SPAN = "struct<start:int,kind:int,end:int,found:string>"
#: Results of a fold are gathered by so many, and so many windows of a candidate are looked at together, so that work is linear in a text.
GATHER, STRETCH = 512, 236


def _folded(items: Column, carried: dict[str, Column], step) -> Column:
    """A fold over ``items`` whose state is ``carried`` and ``out``, an array of spans that grows."""
    none = F.array().cast(f"array<{SPAN}>")
    state = lambda of, out: F.struct(*(of[k].alias(k) for k in carried), out.alias("out"))

    def block(so_far: Column, part: Column) -> Column:
        return bound(F.aggregate(part, state(so_far, none), step), lambda s: state(s, F.concat(so_far["out"], s["out"])))

    count = lambda p: F.ceil(F.size(p) / GATHER).cast("int")
    parts = bound(items, lambda p: F.transform(F.sequence(F.lit(0), count(p)), lambda k: F.slice(p, k * GATHER + 1, F.lit(GATHER))))
    return F.aggregate(parts, state(carried, none), block)


def located(text: Column, pattern: str, kind: int, keep=None) -> Column:
    """Leftmost non-overlapping matches of ``pattern`` as spans with their text; ``keep`` tests a match."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    pieces = F.zip_with(F.split(text, pattern, -1), found, lambda gap, match: F.struct(F.char_length(gap).alias("gap"), match.alias("match")))

    def step(state: Column, piece: Column) -> Column:
        match, begin = piece["match"], state["at"] + piece["gap"]
        end = begin + F.char_length(match)
        span = F.array(F.struct(begin.alias("start"), F.lit(kind).alias("kind"), end.alias("end"), match.alias("found")).cast(SPAN))
        good = match.isNotNull() if keep is None else match.isNotNull() & keep(match)
        return F.struct(F.coalesce(end, begin).alias("at"), F.when(good, F.concat(state["out"], span)).otherwise(state["out"]).alias("out"))

    return F.when(text.rlike(pattern), _folded(pieces, {"at": F.lit(0)}, step)["out"]).otherwise(F.array().cast(f"array<{SPAN}>"))


def uncovered(base: Column, more: Column) -> Column:
    """The spans of ``more`` (by start, none overlaps another) that no span of ``base`` overlaps, in one pass over both."""
    nothing = F.lit(None).cast(SPAN)
    last = len(KINDS) - 1

    def step(state: Column, s: Column) -> Column:
        own, wait = s["kind"] == last, state["wait"]
        stays = F.when(own, F.when(s["start"] >= state["end"], s)).when(s["start"] >= wait["end"], wait)
        done = F.when(own & wait.isNotNull(), F.concat(state["out"], F.array(wait))).otherwise(state["out"])
        # a span that waits and ends before a base span begins still waits for the next of its kind
        return F.struct(F.when(own, state["end"]).otherwise(F.greatest(state["end"], s["end"])).alias("end"), stays.alias("wait"), done.alias("out"))

    both = F.array_sort(F.concat(base, more))
    end = bound(_folded(both, {"end": F.lit(0), "wait": nothing}, step), lambda s: F.concat(s["out"], F.filter(F.array(s["wait"]), lambda w: w.isNotNull())))
    return F.when(F.size(base) == 0, more).otherwise(end)


def best_window(candidate: Column, alphabet: str) -> Column:
    """The highest entropy, in bits a character, of the windows over ``candidate``; characters outside the alphabet count nothing."""
    gain = F.array(*(F.lit(n * math.log2(n) if n else 0.0) for n in range(WINDOW + 2)))
    start = F.struct(F.array_repeat(F.lit(0), len(alphabet)).alias("counts"), F.lit(0.0).alias("sum"), F.lit(1e9).alias("least"))

    def stretch(part: Column) -> Column:
        place = lambda i: F.instr(F.lit(alphabet), F.substring(part, i, F.lit(1)))

        def moved(state: Column, i: Column, inn: Column, out: Column) -> Column:
            at = lambda k: F.coalesce(F.get(state["counts"], k - 1), F.lit(0))
            worth = lambda n: F.element_at(gain, n + 1)
            more = F.when(inn > 0, worth(at(inn) + 1) - worth(at(inn))).otherwise(0.0)
            less = F.when(out > 0, worth(at(out) - 1) - worth(at(out))).otherwise(0.0)
            total = state["sum"] + F.when(inn == out, 0.0).otherwise(more + less)
            counts = F.transform(state["counts"], lambda n, j: n + F.when(j + 1 == inn, 1).otherwise(0) - F.when(j + 1 == out, 1).otherwise(0))
            fresh = F.when(i >= WINDOW, F.least(state["least"], total)).otherwise(state["least"])
            return F.struct(F.when(inn == out, state["counts"]).otherwise(counts).alias("counts"), total.alias("sum"), fresh.alias("least"))

        def step(state: Column, i: Column) -> Column:
            ends = F.struct(place(i).alias("inn"), F.when(i > WINDOW, place(i - WINDOW)).otherwise(0).alias("out"))
            return bound(ends, lambda e: moved(state, i, e["inn"], e["out"]))

        return F.aggregate(F.sequence(F.lit(1), F.char_length(part)), start, step)["least"]

    last = F.floor((F.char_length(candidate) - WINDOW) / STRETCH).cast("int")
    parts = F.transform(F.sequence(F.lit(0), last), lambda k: F.substring(candidate, k * STRETCH + 1, F.lit(STRETCH + WINDOW - 1)))
    return F.lit(math.log2(WINDOW)) - F.array_min(F.transform(parts, stretch)) / WINDOW


def is_secret_like(candidate: Column, allow: tuple[str, ...] = ALLOW) -> Column:
    """Whether a candidate's best window passes the threshold of its class and no allow-list pattern matches."""
    mixed = candidate.rlike("[0-9]") & candidate.rlike("[A-Za-z]")
    (hexes, hex_bits), (tokens, token_bits) = CLASSES["hex"], CLASSES["token"]
    scored = F.when(candidate.rlike("^[0-9a-fA-F]+$"), best_window(F.lower(candidate), hexes) >= hex_bits).otherwise(best_window(candidate, tokens) >= token_bits)
    listed = F.lit(False)
    for pattern in allow:
        listed = listed | candidate.rlike(pattern)
    return F.when(mixed & ~listed, scored).otherwise(F.lit(False))


def scan(df: DataFrame, text: str = "text", key: str = "doc_id", allow: tuple[str, ...] = ALLOW) -> DataFrame:
    """``key`` and ``spans``: array of (start, kind, end, found), by start and then by kind as in ``KINDS``."""
    body = F.col("__text")
    value = lambda m: F.char_length(F.regexp_extract(m, ASSIGN, 2)) >= LEAST["assign"]
    base = F.concat(
        located(body, ASSIGN, 0, value),
        # a greedy run that is long enough is what a bounded repeat finds; runs that are not are never reported
        located(body, f"AKIA[A-Z0-9]{{{LEAST['access'] - 4},}}", 1),
        located(body, f"[0-9a-f]{{{LEAST['hex']},}}", 2),
    )
    more = F.filter(uncovered(F.col("__base"), located(body, TOKEN, 3)), lambda s: is_secret_like(s["found"], allow))
    return (
        df.select(F.col(key), whole_text(text).alias("__text"))
        .withColumn("__base", base)
        .select(F.col(key), F.array_sort(F.concat("__base", more)).alias("spans"))
    )


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in every document: base findings, their digest and all spans."""
    found = scan(table(spark, sf_dir, "documents"))
    name = F.array(*map(F.lit, KINDS))
    line = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(name, s["kind"]), s["start"], s["end"])), ",")
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    return found.select(
        "doc_id",
        *(count(i).alias(f"n_{k}") for i, k in enumerate(KINDS[:3])),
        F.sha2(F.encode(line(F.filter("spans", lambda s: s["kind"] < 3)), "UTF-8"), 256).alias("base_sha256"),
        line(F.col("spans")).alias("spans"),
        count(3).alias("n_entropy"),
    )
