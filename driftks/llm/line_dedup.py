"""Line deduplication across documents by a deletion-neighbourhood join, in built-in functions only.

A line (cut at line feeds, blanks at its ends removed) of ``least`` characters or more is dropped
if it occurred before, or if a line that begins earlier is within one edit of it (a character
changed, added or left out). Earlier means a smaller (id, text hash, line number). The
rule looks at all lines and does not depend on which of them are dropped themselves, so its
result does not depend on the order of work. Shorter lines always stay.

Exact copies: lines are grouped by a 128-bit hash, and only the first place of each goes on. No
occurrence is ever joined to its group, so a line that is everywhere costs a row a task.

Near copies. Two lines of n and n or n+1 characters within one edit agree in their first or in
their last half; lines whose halves nobody shares are done (level 0). The others are cut into
blocks; two such lines agree in all but one block (level 1). What is around a block is hashed by
joining hashes of blocks, so a line's work is linear in its length, and only blocks, never lines,
are carried. For the blocks that somebody else has the surroundings of, all variants with one
character deleted are emitted as hashed keys (level 2). Lines of equal length with one block variant deleted at one place are all within one edit of
each other, so each is joined to the earliest of them only; a line that is itself a variant of a
longer one is joined to it. Each join row is verified by edit distance on the lines.

Edge cases: a null or empty text has one empty line, which stays; rows equal in id and text are one
document and get the same cleaned text; a document that loses all its lines keeps an empty text
(``kept`` = 0); null ids come first in the order; lines of any length are compared whole; an empty
table gives an empty result; other columns pass through ``clean``, which refuses those named as
its counts (``lines`` and ``kept`` unless told otherwise) or as one of ``INTERNAL``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.tables import bound, settled, table, whole_text

LEAST = 20
BLOCK = 32
GRAIN = 8
INTERNAL = {"__k", "__h", "__text", "__pk", "__ph", "__nos", "__stays"}


def _lines(text: str) -> Column:
    return F.split(whole_text(text), "\n", -1)


def _bare(line: Column) -> Column:
    return F.trim(line, F.lit(" \t\r"))


def _half_keys(line: Column, n: Column) -> list[Column]:
    """For the classes n and n-1 of shorter lengths: hashes of the first and of the last half."""
    out = []
    for short in (n, n - 1):
        half = (F.floor(short / (2 * GRAIN)) * GRAIN).cast("int")
        out.append(F.xxhash64(F.lit(0), short, F.left(line, half)))
        out.append(F.xxhash64(F.lit(1), short, F.right(line, half)))
    return out


def first_places(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """Each distinct line of ``docs`` (__k, __h, __text): its first place, its length ``n`` and its half keys."""
    each = docs.select("__k", "__h", F.posexplode(F.transform(_lines("__text"), _bare)).alias("no", "line"))
    each = each.withColumn("n", F.char_length("line")).where(F.col("n") >= least)
    place = F.struct("__k", "__h", "no", "n", *(h.alias(f"half{i}") for i, h in enumerate(_half_keys(F.col("line"), F.col("n")))))
    one = each.select(F.xxhash64("line").alias("x"), F.xxhash64(F.lit(7), "line").alias("y"), place.alias("place"))
    return one.groupBy("x", "y").agg(F.min("place").alias("place")).select("place.*")


def near_candidates(first: DataFrame) -> DataFrame:
    """Places of the lines that share a half with another line of the same or a neighbouring length."""
    keyed = first.select("__k", "__h", "no", F.explode(F.array(*(f"half{i}" for i in range(4)))).alias("half"))
    shared = keyed.groupBy("half").agg(F.count("*").alias("c")).where("c > 1").select("half")
    return keyed.join(shared, "half", "left_semi").select("__k", "__h", "no").distinct()


def _with_lines(docs: DataFrame, places: DataFrame) -> DataFrame:
    """``places`` with the text of their lines; the documents are shuffled once, by (id, text hash)."""
    per = places.groupBy(F.col("__k").alias("pk"), F.col("__h").alias("ph")).agg(F.collect_set("no").alias("nos"))  # of one document
    met = docs.join(per, F.col("__k").eqNullSafe(F.col("pk")) & (F.col("__h") == F.col("ph")))
    lines = F.transform(_lines("__text"), _bare)
    return met.select(F.struct("__k", "__h").alias("doc"), lines.alias("ls"), F.explode("nos").alias("no")).select(F.struct("doc.__k", "doc.__h", "no").alias("place"), F.get("ls", F.col("no")).alias("line"))


def _xor(a: Column, b: Column) -> Column:
    return a.bitwiseXOR(b)


def running_xor(hashes: Column, group: int = 256) -> Column:
    """For each place of an array of longs: the exclusive or of those before it. Groups first, so that work grows little faster than the array."""

    def prefixes(some: Column) -> Column:
        """The exclusive or of the first 0, 1, 2, ... of ``some``."""
        return F.aggregate(some, F.array(F.lit(0).cast("long")), lambda out, x: F.concat(out, F.array(_xor(F.element_at(out, -1), x))))

    def joined(local: Column) -> Column:
        tops = prefixes(F.transform(local, lambda p: F.element_at(p, -1)))
        own = lambda before: F.flatten(F.transform(local, lambda p, g: F.transform(F.slice(p, F.lit(1), F.size(p) - 1), lambda x: _xor(x, F.get(before, g)))))
        return bound(tops, own)

    starts = F.filter(F.sequence(F.lit(0), F.size(hashes), F.lit(group)), lambda g: g < F.size(hashes))
    return bound(F.transform(starts, lambda g: prefixes(F.slice(hashes, g + 1, group))), joined)


def _blocks(line: Column, size: int) -> Column:
    """The line cut into blocks of ``size`` characters, in one pass (a substring is found from the line's begin)."""
    return F.regexp_extract_all(line, F.lit(f"(?s).{{1,{size}}}"), F.lit(0))


def block_keys(line: Column, size: int = BLOCK) -> Column:
    """Of every block j of a line: ``longer``, a hash ``around`` of all that is not in the block, and the block's text ``inner``.

    Two lines of one length that differ in one character have one block j and ``around`` in common. A line is
    also cut as one with a character too many, in the block j (``longer``): what follows is taken one
    character later, so that it agrees with the line that lacks the character. Hashes of blocks carry their
    number and are joined by exclusive or, so the work is linear in the line.
    """

    def of(n: Column, parts: Column, later: Column) -> Column:
        own = F.transform(parts, lambda b, i: F.xxhash64(i, b))
        moved = F.transform(later, lambda b, i: F.xxhash64(i, b))
        total = lambda h: F.aggregate(h, F.lit(0).cast("long"), _xor)

        def keys(own: Column, moved: Column, all_own: Column, all_moved: Column, before: Column, before_moved: Column) -> Column:
            equal = F.transform(parts, lambda b, j: F.struct(F.lit(False).alias("longer"), F.xxhash64(n, j, _xor(all_own, F.get(own, j))).alias("around"), b.alias("inner")))
            beyond = lambda j: _xor(all_moved, _xor(F.get(before_moved, j), F.get(moved, j)))
            inner = lambda j: F.concat(F.get(parts, j), F.left(F.coalesce(F.get(parts, j + 1), F.lit("")), F.lit(1)))
            longer = F.transform(later, lambda b, j: F.struct(F.lit(True).alias("longer"), F.xxhash64(n - 1, j, _xor(F.get(before, j), beyond(j))).alias("around"), inner(j).alias("inner")))
            return F.concat(equal, longer)

        return bound(F.struct(own.alias("o"), moved.alias("m")), lambda h: bound(
            F.struct(total(h["o"]).alias("o"), total(h["m"]).alias("m"), running_xor(h["o"]).alias("p"), running_xor(h["m"]).alias("q")),
            lambda t: keys(h["o"], h["m"], t["o"], t["m"], t["p"], t["q"]),
        ))

    cut = F.struct(F.char_length(line).alias("n"), _blocks(line, size).alias("p"), _blocks(F.substring(line, 2, 2**31 - 1), size).alias("s"))
    return bound(cut, lambda c: of(c["n"], c["p"], c["s"]))


def within_one_edit(a: Column, b: Column, size: int = BLOCK) -> Column:
    """Whether two lines differ by one character changed, added or left out at most, in time linear in them (``levenshtein`` takes the square).

    Blocks tell roughly where the lines part; after that place, the rest must be equal but for the one character.
    """

    def decided(cut: Column) -> Column:
        shared = F.zip_with(cut["a"], cut["b"], lambda x, y: F.coalesce(x, F.lit("")) == F.coalesce(y, F.lit("")))
        block = lambda side, i: F.coalesce(F.get(cut[side], i), F.lit(""))

        def parted(i: Column) -> Column:
            alike = F.filter(F.sequence(F.lit(1), F.lit(size)), lambda k: F.left(block("a", i), k) == F.left(block("b", i), k))
            at = i * size + F.size(alike) + 1  # of the first character that differs
            rest = lambda line, skip: F.substring(line, at + skip, F.lit(2**31 - 1))
            return (
                F.when(cut["m"] == cut["n"], rest(a, 1) == rest(b, 1))
                .when(cut["n"] == cut["m"] + 1, rest(a, 1) == rest(b, 0))
                .when(cut["m"] == cut["n"] + 1, rest(a, 0) == rest(b, 1))
                .otherwise(False)
            )

        first = (F.array_position(shared, False) - 1).cast("int")
        return bound(first, lambda i: F.when(i < 0, True).otherwise(parted(i)))

    return bound(F.struct(_blocks(a, size).alias("a"), _blocks(b, size).alias("b"), F.char_length(a).alias("n"), F.char_length(b).alias("m")), decided)


def near_copies(lines: DataFrame, block: int = BLOCK) -> DataFrame:
    """Places of ``lines`` (place, line; distinct lines) that an earlier line within one edit precedes."""
    blocks = lines.select("place", F.explode(block_keys(F.col("line"), block)).alias("b")).select("place", "b.*")
    shared = blocks.groupBy("around").agg(F.count("*").alias("c"), F.count_if(~F.col("longer")).alias("own")).where("c > 1 and own > 0").select("around")
    live = settled(blocks.join(shared, "around", "left_semi"))

    def emitted(rows: DataFrame) -> DataFrame:
        i = F.explode(F.sequence(F.lit(1), F.char_length("inner"))).alias("i")
        rows = rows.where("inner <> ''").select("place", "around", "inner", i)
        rest = F.concat(F.left("inner", F.col("i") - 1), F.substring(F.col("inner"), F.col("i") + 1, F.char_length("inner")))
        return rows.select("place", "around", "i", F.xxhash64("around", rest).alias("key"))

    equal, longer = emitted(live.where("not longer")), emitted(live.where("longer"))
    whole = live.where("not longer").select(F.col("place").alias("other"), F.xxhash64("around", "inner").alias("key"))
    earliest = equal.groupBy("key", "i").agg(F.min("place").alias("other"))
    changed = equal.join(earliest, ["key", "i"]).where("other < place").select("place", "other")
    added = longer.join(whole, "key").where("other < place").select("place", "other")
    before = longer.groupBy("key").agg(F.min("place").alias("place"))
    lost = before.join(whole, "key").where("place < other").select(F.col("other").alias("place"), F.col("place").alias("other"))
    pairs = changed.union(added).union(lost).distinct()
    by = lambda name: lines.select(F.col("place").alias(name), F.col("line").alias(f"{name}_line"))
    met = pairs.join(by("place"), "place").join(by("other"), "other")
    return met.where(within_one_edit(F.col("place_line"), F.col("other_line"))).select("place").distinct()


def clean(df: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, block: int = BLOCK, least_exact: int | None = None, counts: tuple[str, str] = ("lines", "kept")) -> DataFrame:
    """``df`` with ``text`` cut to the lines that stay, and their numbers before and after, named by ``counts``.

    ``least_exact``: characters from which exact repeats go (``least`` if not given); ``least`` holds for near ones.
    """
    taken = [c for c in df.columns if c in counts or c in INTERNAL]
    if taken:
        raise ValueError(f"columns named {', '.join(taken)} would be overwritten: rename them first")
    exact = least if least_exact is None else least_exact
    whole = df.withColumn("__k", F.col(key)).withColumn("__h", F.xxhash64(whole_text(text))).withColumn("__text", whole_text(text))
    docs = whole.select("__k", "__h", "__text")
    first = settled(first_places(docs, exact))
    lines = settled(_with_lines(docs, near_candidates(first.where(F.col("n") >= least))).groupBy("place").agg(F.first("line").alias("line")))
    near = near_copies(lines, block).select(F.col("place.__k").alias("nk"), F.col("place.__h").alias("nh"), F.col("place.no").alias("nn"))
    same = F.col("__k").eqNullSafe(F.col("nk")) & (F.col("__h") == F.col("nh")) & (F.col("no") == F.col("nn"))
    stay = first.select("__k", "__h", "no").join(near, same, "left_anti")
    per = stay.groupBy(F.col("__k").alias("__pk"), F.col("__h").alias("__ph")).agg(F.collect_list("no").alias("__nos"))  # of one document
    met = whole.join(per, F.col("__k").eqNullSafe(F.col("__pk")) & (F.col("__h") == F.col("__ph")), "left")

    def stays(parts: Column) -> Column:
        short = F.filter(F.transform(parts, lambda s, i: F.struct(i.alias("i"), s.alias("s"))), lambda p: F.char_length(_bare(p["s"])) < exact)
        long = F.transform(F.coalesce("__nos", F.array().cast("array<int>")), lambda i: F.struct(i.alias("i"), F.get(parts, i).alias("s")))
        return F.transform(F.array_sort(F.concat(short, long)), lambda p: p["s"])

    out = met.withColumn("__stays", bound(_lines("__text"), stays)).withColumn(counts[0], F.size(_lines("__text"))).withColumn(counts[1], F.size("__stays"))
    out = out.withColumn(text, F.array_join("__stays", "\n"))
    return out.select(*df.columns, *counts)


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents without the lines that occurred before, exactly or within one edit."""
    return clean(table(spark, sf_dir, "documents").select("doc_id", "text"))


OP8_SQL = f"""
with parts as (
  select doc_id, string_split(coalesce(text, ''), chr(10)) as ls from documents
), each as (
  select doc_id, unnest(ls) as raw, generate_subscripts(ls, 1) - 1 as no from parts
), bare as (
  select doc_id, no, raw, trim(raw, ' ' || chr(9) || chr(13)) as line from each
), firsts as (
  select line, min((doc_id, no)) as place from bare where length(line) >= {LEAST} group by line
), halves as (
  select line, place, n, n // 2 as h, left(line, n // 2) as a, right(line, n // 2) as b from (
    select line, place, unnest([length(line), length(line) - 1]) as n from firsts)
), near as (
  select distinct y.place from halves x join halves y on x.n = y.n and x.a = y.a
    and x.place < y.place and abs(length(x.line) - length(y.line)) <= 1 and levenshtein(x.line, y.line) <= 1
  union
  select distinct y.place from halves x join halves y on x.n = y.n and x.b = y.b
    and x.place < y.place and abs(length(x.line) - length(y.line)) <= 1 and levenshtein(x.line, y.line) <= 1
), flagged as (
  select bare.*, length(line) < {LEAST} or ((doc_id, no) in (select place from firsts) and (doc_id, no) not in (select place from near)) as stays from bare
)
select doc_id, coalesce(string_agg(raw, chr(10) order by no) filter (where stays), '') as text,
       count(*)::int as lines, (count(*) filter (where stays))::int as kept
from flagged group by doc_id
"""
