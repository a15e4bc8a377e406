"""Line de-duplication by content-defined chunks of several lines, and by runs of lines of over fifty words.

A rolling hash over the hashes of neighbouring lines chooses the boundaries: a chunk ends where
the hash is smaller than the hashes around it, so a boundary depends on a few lines alone and
shifts with them, and every chunk inside a text holds two lines at least.

A shared passage may be too short in lines to hold a whole chunk. So from each line with words the shortest
run that has more than ``run_words`` words is taken too, forwards and backwards: a shared run of more words holds
the run forwards of each of its lines, or else that line lies in the run backwards of its last one.

Chunks and runs are fragments: they are counted by hash over all documents, and those whose hash occurs again are compared
with the bytes of the first one. The first occurrence, by (doc_id as text, hash of the text, place),
stays, and the lines of all others are removed; a line that is removed is always left at an earlier place.

All of it is DataFrame functions. Fragments are found once, and checkpointed as places and hashes; they travel as hashes, but for those whose hash repeats.
Each count is pre-aggregated per task, and the join of repeated fragments is a plain one whose
skewed partitions adaptive execution splits.

Defined results: a null or empty text has no fragments and stays as it is; lines without a word
never make a chunk multi-line; a single line is never removed for itself, however often it occurs, if it has
at most ``run_words`` words; very long texts are taken whole, in one row's arrays of lines; a fragment that overlaps its own first occurrence, as in a line
said many times over, stays; one whose hash equals another's but not its bytes stays;
rows with equal doc_id and text are treated alike, so the first occurrence stays
in each of them; an empty table gives an empty one; other columns are carried as they are, with
n_chars set to the new length; n_removed_chunks counts the unbroken stretches of lines that went.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, keyed, n_words


@dataclass(frozen=True)
class Chunking:
    """A chunk can be removed if it has ``min_lines`` lines with words and ``min_chars`` characters; a run if it has over ``run_words`` words."""

    min_lines: int = 2
    min_chars: int = 60
    run_words: int = 50


#: A fragment's code: its first line, from 0, times this, and its number of lines.
LINES = 1 << 32
#: Lines that mostly have a run's words.
NEAR = 8


def _rolled(h: Column) -> Column:
    """Of each line's hash, a hash of it and of the line before: a window of two that rolls on by rotation and xor."""
    turned = lambda x: F.call_function("shiftleft", x, F.lit(1)).bitwiseOR(F.call_function("shiftrightunsigned", x, F.lit(63)))
    before = F.concat(F.array(F.lit(0).cast("long")), F.slice(h, 1, F.greatest(F.size(h) - 1, F.lit(0))))
    return F.zip_with(before, h, lambda a, b: F.xxhash64(turned(a).bitwiseXOR(b)))


def _ends(rolled: Column) -> Column:
    """Places, from 1, of lines that end a chunk: minima of the rolling hash, and the last line."""
    def ends(x: Column, i: Column) -> Column:
        least = (i > 0) & (x < F.get(rolled, i - 1)) & (x <= F.get(rolled, i + 1))
        return F.when((i == F.size(rolled) - 1) | least, i + 1)

    return F.filter(F.transform(rolled, ends), lambda x: x.isNotNull())


def _code(first: Column, n: Column) -> Column:
    return first.cast("long") * LINES + n


def _place(code: Column) -> tuple[Column, Column]:
    """First line, from 0, and number of lines."""
    return F.call_function("shiftright", code, F.lit(32)).cast("int"), code.bitwiseAND(F.lit(LINES - 1)).cast("int")


def _runs(full: Column, c: Chunking) -> Column:
    """Codes of the shortest runs of over run_words words from each line with words on, and back from it; each such line has a word at least, so run_words + 1 of them do."""
    def run(near: Column, far: Column) -> Column:
        """Words and last line of the shortest beginning of the lines that has enough; the far ones are looked at where the near ones have too few."""
        none = F.struct(F.lit(0).cast("long").alias("w"), F.lit(0).alias("i"))
        step = lambda a, x: F.when(a["w"] > c.run_words, a).otherwise(F.struct((a["w"] + x["w"]).alias("w"), x["i"].alias("i")))
        first = F.aggregate(near, none, step)
        return F.when(first["w"] > c.run_words, first).otherwise(F.aggregate(far, first, step))

    def code(x: Column, found: Column) -> Column:
        first, last = F.least(x["i"], found["i"]), F.greatest(x["i"], found["i"])
        return F.when(found["w"] > c.run_words, _code(first, last - first + 1))

    most = c.run_words + 1
    some = min(NEAR, most)

    def before(i: Column, skip: int, n: int) -> Column:
        """The n lines before the last ``skip`` ones up to place i, from 0, last first."""
        end = F.greatest(i + 1 - skip, F.lit(0))
        return F.reverse(F.slice(full, F.greatest(end - n, F.lit(0)) + 1, F.least(end, F.lit(n))))

    on = F.transform(full, lambda x, i: code(x, run(F.slice(full, i + 1, some), F.slice(full, i + 1 + some, most - some))))
    back = F.transform(full, lambda x, i: code(x, run(before(i, 0, some), before(i, some, most - some))))
    return F.concat(on, back)


def fragments(docs: DataFrame, keep: list[Column], c: Chunking = Chunking()) -> DataFrame:
    """The kept columns, and the array _fragments of (code, k): place and hash of the lines of each fragment."""
    names = docs.select(*keep).columns
    step = docs.select(*keep, F.split(F.coalesce("text", F.lit("")), "\n", -1).alias("_lines"))
    step = step.select("*", F.transform("_lines", lambda x: F.xxhash64(x)).alias("_hashes"), F.transform("_lines", lambda x, i: F.struct(i.alias("i"), n_words(x).alias("w"))).alias("_words"))
    step = step.select("*", _rolled(F.col("_hashes")).alias("_rolled"), F.filter("_words", lambda x: x["w"] > 0).alias("_full"))
    step = step.select("*", _ends(F.col("_rolled")).alias("_ends"))
    lines, ends = F.col("_lines"), F.col("_ends")

    def chunk(end: Column, i: Column) -> Column:
        first = F.when(i == 0, F.lit(0)).otherwise(F.get(ends, i - 1))
        n = end - first
        chars = F.aggregate(F.slice(lines, first + 1, n), n - 1, lambda a, x: a + F.length(x))
        full = F.size(F.filter(F.slice("_words", first + 1, n), lambda x: x["w"] > 0))
        return F.when((chars >= c.min_chars) & (full >= c.min_lines), _code(first, n))

    codes = F.array_distinct(F.array_compact(F.concat(F.transform(ends, chunk), _runs(F.col("_full"), c))))
    step = step.select(*names, "_hashes", codes.alias("_codes"))

    def hashed(code: Column) -> Column:
        first, n = _place(code)
        return F.struct(code.alias("code"), F.xxhash64(F.slice("_hashes", first + 1, n)).alias("k"))

    return step.select(*names, F.transform("_codes", hashed).alias("_fragments"))


def removals(docs: DataFrame, rows: DataFrame, c: Chunking = Chunking()) -> DataFrame:
    """(_id, _h, gone): of documents that lose lines, the codes of the fragments that go; rows are docs as _without() has them."""
    # read twice, and dear to make: checkpointed, as one short array a document
    parts = cut(fragments(docs, [keyed(F.col("doc_id")).alias("_id"), F.xxhash64("text").alias("_h")], c))
    parts = parts.select("_id", "_h", F.explode("_fragments").alias("f")).select("_id", "_h", "f.code", "f.k")
    place = F.struct("_id", "_h", "code")
    again = parts.groupBy("k").agg(F.min(place).alias("first"), F.max(place).alias("last")).filter("first <> last").select("k", "first")
    repeated = parts.join(again, "k")
    (line, n), (first_line, _) = _place(F.col("code")), _place(F.col("first.code"))
    own = (F.col("_id") == F.col("first._id")) & (F.col("_h") == F.col("first._h"))
    marks = repeated.filter((place == F.col("first")) | ~own | (line >= first_line + n))
    marks = marks.groupBy("_id", "_h").agg(F.collect_set(F.struct("code", "k", (place == F.col("first")).alias("is_first"))).alias("marks"))
    marks = marks.withColumnsRenamed({"_id": "id", "_h": "h"})
    # always true, but it needs whole rows, so that this join and the last one read one shuffle of them
    whole = F.xxhash64("_row", "marks") >= F.lit(-(1 << 63))
    held = rows.join(marks, (F.col("_id") == F.col("id")) & (F.col("_h") == F.col("h")) & whole).select("_id", "_h", F.split("text", "\n", -1).alias("_lines"), "marks")

    def told(m: Column) -> Column:
        first, n = _place(m["code"])
        return F.struct(m["code"].alias("code"), m["k"].alias("k"), m["is_first"].alias("is_first"), F.array_join(F.slice("_lines", first + 1, n), "\n").alias("own"))

    held = held.select("_id", "_h", F.explode(F.transform("marks", told)).alias("m")).select("_id", "_h", "m.*")
    kept = held.filter("is_first").dropDuplicates(["k"]).select("k", F.col("own").alias("same"))
    gone = held.filter("not is_first").select("_id", "_h", "code", "k", "own").join(kept, "k").filter("own = same")
    return gone.groupBy("_id", "_h").agg(F.collect_set("code").alias("gone"))


def dedup(docs: DataFrame, c: Chunking = Chunking()) -> DataFrame:
    """The rows of docs in their own columns, without the chunks that an earlier row or place has; rows may be left without text."""
    return _without(docs, c).select(*docs.columns)


def _without(docs: DataFrame, c: Chunking) -> DataFrame:
    other = [x for x in docs.columns if x not in ("text", "n_chars")]
    rows = docs.select(F.struct(*[F.col(f"`{x}`") for x in other]).alias("_row"), keyed(F.col("doc_id")).alias("_id"), F.xxhash64("text").alias("_h"), "text")
    out = rows.join(removals(docs, rows, c), ["_id", "_h"], "left")

    def lines(code: Column) -> Column:
        first, n = _place(code)
        return F.sequence(first, first + n - 1)

    out = out.select("_row", "text", F.split("text", "\n", -1).alias("_lines"), F.array_sort(F.array_distinct(F.flatten(F.transform("gone", lines)))).alias("_gone"))
    left = F.transform(F.array_except(F.sequence(F.lit(0), F.size("_lines") - 1), "_gone"), lambda i: F.get("_lines", i))
    text = F.when(F.col("_gone").isNull(), F.col("text")).otherwise(F.array_join(left, "\n"))
    stretches = F.size(F.filter(F.transform("_gone", lambda x, i: F.coalesce(x - F.get("_gone", i - 1) > 1, F.lit(True))), lambda x: x))
    out = out.select("_row", text.alias("text"), F.when(F.col("_gone").isNull(), 0).otherwise(stretches).cast("long").alias("n_removed_chunks"), (F.coalesce(F.length("text"), F.lit(0)) - F.coalesce(F.length(text), F.lit(0))).cast("long").alias("n_removed_chars"))

    def column(x: str) -> Column:
        if x == "text":
            return F.col("text")
        return F.length("text").cast(docs.schema[x].dataType).alias(x) if x == "n_chars" else F.col(f"_row.`{x}`").alias(x)

    return out.select(*map(column, docs.columns), *[x for x in ("n_removed_chunks", "n_removed_chars") if x not in docs.columns])


def measure(docs: DataFrame, c: Chunking = Chunking()) -> DataFrame:
    """One row per row of docs: doc_id, its text without repeated chunks, and what was removed."""
    return _without(docs.select("doc_id", "text"), c)
