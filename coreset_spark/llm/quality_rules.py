"""Line-first cleaning: rules judge each line, failed lines go, and a document that loses too much text is rejected.

Everything is built from DataFrame functions over the arrays of one row, so no row is ever
exploded or shuffled and a long document costs n log n.

Defined results: a null or empty text has no words and fails the base rules; a blank line is
neutral, it neither fails nor counts as lost text; repeated rows are judged alike, each by
itself; an empty table gives an empty one; columns of the input are never read by another
name, so clashing extra columns are kept by :func:`clean` and ignored by :func:`measure`.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import only, words

# Lower-case phrases of pages' frames, never of their prose.
BOILERPLATE = (
    "all rights reserved", "cookie policy", "privacy policy", "terms of use", "terms of service",
    "enable javascript", "sign in to", "subscribe to our", "click here", "skip to content",
    "lorem ipsum", "powered by", "share this",
)
SYMBOLS = "#*$%&|<>"  # none is special within brackets


@dataclass(frozen=True)
class Rules:
    """Limits of the base rules and of the rules for lines; a share is of the line's or the document's words."""

    min_words: int = 50
    max_repeat_percent: int = 50
    max_lost_percent: int = 30
    max_symbol_percent: int = 30
    max_shout_percent: int = 50
    max_separator_percent: int = 20
    terminal: str = ".!?…:;。！？"
    closing: str = "\"'”’»)]"
    boilerplate: tuple[str, ...] = BOILERPLATE


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _has_word(line: Column) -> Column:
    return line.rlike(r"[^\x20\x09-\x0D]")


def _framed(low: Column, rules: Rules) -> Column:
    """Whether a lower-case text holds a boilerplate phrase."""
    out = F.lit(False)
    for phrase in rules.boilerplate:
        out = out | F.contains(low, F.lit(phrase))
    return out


def line_fails(line: Column, rules: Rules = Rules(), marked: Column | None = None, framed: Column | None = None) -> Column:
    """Whether a line with words breaks a rule: punctuation, navigation or boilerplate.

    marked and framed: whether the whole text has any mark or phrase at all, so that the rules
    on them are tried only where they can fail.
    """
    ws = words(line)
    n = F.size(ws)
    end = rf"[{''.join(chr(92) + c for c in rules.terminal)}][{''.join(chr(92) + c for c in rules.closing)}]*[\x20\x09-\x0D]*$"
    share = lambda pattern, most: F.size(F.filter(ws, lambda w: w.rlike(pattern))) * 100 > n * most
    shouted = line.rlike("!!") & share("!!$", rules.max_shout_percent)
    symbolic = line.rlike("[#*$%&<>]{2}") & share("[#*$%&<>]{2}$", rules.max_symbol_percent)
    listed = line.rlike("[|»›•·]") & share("^[|»›•·>/]+$", rules.max_separator_percent)
    by_marks, by_phrase = shouted | symbolic | listed, _framed(F.lower(line), rules)
    broken = ~line.rlike(end) | (by_marks if marked is None else marked & by_marks) | (by_phrase if framed is None else framed & by_phrase)
    return _has_word(line) & broken


def _guarded(docs: DataFrame, rules: Rules, keep: list[Column]) -> DataFrame:
    """The kept columns, the lines, and whether the text has any mark or phrase that a rule looks for."""
    text = F.coalesce(F.col("text"), F.lit(""))
    step = docs.select(*keep, text.alias("text"), _lines(text).alias("_lines"), text.rlike("[#*$%&|<>!»›•·]").alias("_marked"), _framed(F.lower(text), rules).alias("_framed"))
    return step.select("*", words(F.col("text")).alias("_words"))


def _windows(ws: Column, bits: Column) -> Column:
    """Of each window of three words, a hash with the window's place in its low bits; sorted."""
    n = F.greatest(F.size(ws) - 2, F.lit(0))
    each = F.transform(
        F.slice(ws, 1, n),
        lambda _, i: F.coalesce(F.call_function("shiftleft", F.xxhash64(F.get(ws, i), F.get(ws, i + 1), F.get(ws, i + 2)), bits).bitwiseOR(i.cast("long")), F.lit(0).cast("long")),
    )
    return F.sort_array(each)


def _exact_windows(ws: Column) -> Column:
    """As :func:`_windows`, by the windows' own words: (text, place), sorted."""
    n = F.greatest(F.size(ws) - 2, F.lit(0))
    return F.sort_array(F.transform(F.slice(ws, 1, n), lambda _, i: F.struct(F.concat_ws(" ", F.get(ws, i), F.get(ws, i + 1), F.get(ws, i + 2)).alias("x"), i.alias("i"))))


def _neighbours(s: Column, join) -> Column:
    n = F.greatest(F.size(s) - 1, F.lit(0))
    return F.filter(F.zip_with(F.slice(s, 1, n), F.slice(s, 2, n), join), lambda x: x.isNotNull())


def _covered(places: Column) -> Column:
    """Words within three of a sorted place: the union of spans of three."""
    span = F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last"))
    return F.aggregate(
        places, span, lambda a, i: F.struct((a["n"] + F.least(F.lit(3), i - a["last"])).alias("n"), i.alias("last")), lambda a: a["n"]
    ).cast("long")


def _repeated_words(ws: Column, windows: Column, bits: Column) -> Column:
    """Words that some window found twice or more covers.

    Windows of one hash lie side by side. Where two of them differ in their words after all,
    the document is judged by the windows' own words instead.
    """
    place = lambda x: x.bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), bits) - 1).cast("int")
    before = lambda i: F.get(windows, i - 1)
    twins = F.filter(F.transform(windows, lambda x, i: F.when((i > 0) & (F.call_function("shiftright", x.bitwiseXOR(before(i)), bits) == 0), i)), lambda i: i.isNotNull())

    def pair(k: Column) -> Column:
        i, j = place(before(k)), place(F.get(windows, k))
        same = (F.get(ws, i) == F.get(ws, j)) & (F.get(ws, i + 1) == F.get(ws, j + 1)) & (F.get(ws, i + 2) == F.get(ws, j + 2))
        return F.when(same, F.array(i, j)).otherwise(F.array(F.lit(-1)))

    flat = lambda pairs: F.sort_array(F.array_distinct(F.flatten(pairs)))
    near = flat(F.transform(twins, pair))
    exact = flat(_neighbours(_exact_windows(ws), lambda a, b: F.when(a["x"] == b["x"], F.array(a["i"], b["i"]))))
    return F.when(F.array_contains(near, -1), _covered(exact)).otherwise(_covered(near))


def _base(step: DataFrame, rules: Rules) -> DataFrame:
    """Adds the base counts and base_failed."""
    text, ws, lines = F.col("text"), F.col("_words"), F.col("_lines")
    full = F.filter(lines, _has_word)
    step = step.select(
        "*",
        F.size(ws).cast("long").alias("n_words"),
        F.length(F.array_join(ws, "")).cast("long").alias("word_chars"),
        F.when(F.col("_marked"), F.length(text) - F.length(F.regexp_replace(text, f"[{SYMBOLS}]+", ""))).otherwise(0).cast("long").alias("n_symbols"),
        (F.size(full) - F.size(F.array_distinct(full))).cast("long").alias("n_dup_lines"),
        F.coalesce(F.length(F.bin(F.size(ws))), F.lit(1)).alias("_bits"),
    )
    step = step.select("*", _windows(ws, F.col("_bits")).alias("_windows"))
    step = step.select("*", _repeated_words(ws, F.col("_windows"), F.col("_bits")).alias("n_repeat_words"))
    failed = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.max_repeat_percent * F.col("n_words"))
    return step.select("*", failed.alias("base_failed"))


def _judged(docs: DataFrame, rules: Rules, keep: list[Column]) -> DataFrame:
    """Adds the failed lines, and the verdict: the words of failed lines stay within the allowed loss."""
    step = _base(_guarded(docs, rules, keep), rules)
    step = step.select("*", F.filter("_lines", lambda x: line_fails(x, rules, F.col("_marked"), F.col("_framed"))).alias("_failed"))
    step = step.select("*", F.aggregate("_failed", F.lit(0).cast("long"), lambda a, x: a + F.size(words(x))).alias("n_lost_words"))
    within = (F.col("n_words") > F.col("n_lost_words")) & (F.col("n_lost_words") * 100 <= F.col("n_words") * rules.max_lost_percent)
    return step.select("*", (~F.col("base_failed") & within).alias("kept"))


def measure(docs: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """One row per document: its base counts, base_failed, kept, and what the rules for lines took."""
    out = _judged(docs, rules, [F.col("doc_id")])
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.size("_failed").cast("long").alias("n_failed_lines"), "n_lost_words")


def clean(docs: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """The documents that are kept, in their own columns, without the lines that failed; n_chars follows the text."""
    names = [c for c in docs.columns if c not in ("text", "n_chars")]
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("_row"), F.col("text"))
    out = only(_judged(packed, rules, [F.col("_row")]), F.col("kept"))
    left = F.filter("_lines", lambda x: ~line_fails(x, rules, F.col("_marked"), F.col("_framed")))
    out = out.select("_row", F.when(F.size("_failed") == 0, F.col("text")).otherwise(F.array_join(left, "\n")).alias("text"))

    def column(c: str) -> Column:
        if c == "text":
            return F.col("text")
        return F.length("text").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col(f"_row.`{c}`").alias(c)

    return out.select(*map(column, docs.columns))
