"""Quotation linking: nested quotes are parsed, joined to the messages they come from, and conversations put in reply order.

A line's quote level is the number of leading ``>`` marks. A run of lines of one level is a
passage; its hash, and the hashes of its lines, after white space and case are evened out, are
joined to the same hashes of all messages' own text. Each hash has one source per conversation, the
earliest turn, and one in the whole corpus, the earliest message, so the join never multiplies:
sources are pre-aggregated minima, and a line that every message has costs no more than a rare one.

A message answers the latest earlier turn of its conversation that it quotes at the first level; else
the message of another, earlier conversation; else the turn before it. Deeper levels quote what
the answered message quoted, and are linked and counted alike. The result has one row per message, without
quotes and the lines that introduce them, in reply order: thread, depth in the thread of
conversations, turn.

Defined results: a null text has no words and no quotes, and stays null; rows that repeat (conv_id, turn)
are messages of their own; a message never answers itself or a later one; a conversation without links
is its own thread; null ids come first in their order and link to nothing; rows that agree in all are ordered
anyhow; a very long text is one row's lines; an empty table gives an empty one; only conv_id, turn, role and text are read,
whatever other columns are called. Rows are numbered by one global sort, so a conversation of any length takes as many tasks as it fills.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.ranks import row_numbers
from .common import cut, keyed

_QUOTED = r"^[ \t]*>"
_MARKS = r"^[ \t]*((?:>[ \t]?)*)"
#: Lines that introduce a quote, such as "On ... wrote:".
_INTRODUCED = r"(?i)^[ \t]*(?:on|am|le|el)\b.*\b(?:wrote|schrieb|écrit|escribió)\s*:?[ \t]*$"


def _even(text: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(text, r"\s+", " ")))


def _level(line: Column) -> Column:
    return F.length(F.regexp_replace(F.regexp_extract(line, _MARKS, 1), r"[ \t]", ""))


def parsed(messages: DataFrame) -> DataFrame:
    """Adds own (text without quotes) and quoted: array of (level, line), in order."""
    lines = F.split("text", "\n", -1)
    step = messages.select("*", lines.alias("_lines"), F.coalesce(F.col("text").rlike(r"(?m)" + _QUOTED), F.lit(False)).alias("_quotes"))
    follows = lambda i: F.coalesce(F.get("_lines", i + 1), F.lit("")).rlike(_QUOTED)
    stays = lambda x, i: ~x.rlike(_QUOTED) & ~(x.rlike(_INTRODUCED) & follows(i))
    own = F.when(F.col("_quotes"), F.trim(F.array_join(F.filter("_lines", stays), "\n"))).otherwise(F.col("text"))
    none = F.array().cast("array<struct<level:int,line:string>>")
    quoted = F.when(F.col("_quotes"), F.transform(F.filter("_lines", lambda x: x.rlike(_QUOTED)), lambda x: F.struct(_level(x).alias("level"), _even(F.regexp_replace(x, _MARKS, "")).alias("line")))).otherwise(none)
    return step.select(*messages.columns, own.alias("own"), quoted.alias("quoted"))


def _sources(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, h) of what can be quoted: a message's own text as a whole, and each of its lines of some length."""
    whole = F.array(_even(F.col("own")))
    lines = F.transform(F.split("own", "\n", -1), _even)
    units = F.filter(F.array_union(whole, lines), lambda x: F.length(x) >= 8)
    return messages.filter("conv_id is not null and turn is not null").select("conv_id", "turn", F.explode(units).alias("u")).select("conv_id", "turn", F.xxhash64("u").alias("h"), F.xxhash64("u", F.lit(1)).alias("g"))


def linked(messages: DataFrame) -> DataFrame:
    """(conv_id, turn, level, to_conv, to_turn): each quoted line's or passage's source, where one is found before it."""
    quotes = messages.filter(F.size("quoted") > 0).select("conv_id", "turn", "quoted")
    levels = quotes.select("conv_id", "turn", "quoted", F.explode(F.array_distinct(F.transform("quoted", lambda q: q["level"]))).alias("level"))
    own = F.transform(F.filter("quoted", lambda q: q["level"] == F.col("level")), lambda q: q["line"])
    units = F.filter(F.array_union(F.array(_even(F.array_join(own, " "))), own), lambda x: F.length(x) >= 8)
    asked = levels.select("conv_id", "turn", "level", F.explode(units).alias("u")).select("conv_id", "turn", "level", F.xxhash64("u").alias("h"), F.xxhash64("u", F.lit(1)).alias("g")).distinct()
    sources = _sources(messages)
    near = sources.groupBy("conv_id", "h", "g").agg(F.min("turn").alias("to_turn"))
    far = sources.groupBy("h", "g").agg(F.min(F.struct("conv_id", "turn")).alias("to"))
    here = asked.join(near, ["conv_id", "h", "g"], "left").withColumn("to_turn", F.when(F.col("to_turn") < F.col("turn"), F.col("to_turn")))
    there = here.join(far, ["h", "g"], "left")
    away = (F.col("to.conv_id") < F.col("conv_id")) & F.col("to_turn").isNull()
    conv = F.when(F.col("to_turn").isNotNull(), F.col("conv_id")).when(away, F.col("to.conv_id"))
    turn = F.when(F.col("to_turn").isNotNull(), F.col("to_turn")).when(away, F.col("to.turn"))
    return there.select("conv_id", "turn", "level", conv.alias("to_conv"), turn.alias("to_turn")).filter("to_conv is not null")


def _threads(links: DataFrame, most: int = 64) -> DataFrame:
    """(conv_id, thread, depth) of conversations that answer others, by pointer doubling; links (conv_id, up) go to smaller ids."""
    at = cut(links.select("conv_id", F.col("up").alias("thread"), F.lit(1).alias("depth")))
    for _ in range(most):
        up = at.select(F.col("conv_id").alias("thread"), F.col("thread").alias("over"), F.col("depth").alias("more"))
        step = at.join(up, "thread", "left")
        new = cut(step.select("conv_id", F.coalesce("over", "thread").alias("thread"), (F.col("depth") + F.coalesce("more", F.lit(0))).alias("depth"), F.col("over").isNotNull().alias("moved")))
        at = new.drop("moved")
        if new.filter("moved").isEmpty():
            return at
    raise RuntimeError("threads did not settle")


def conversations(messages: DataFrame) -> DataFrame:
    """One row per message: conv_id, turn, role, text without quotes, n_quoted_lines, n_links, reply_conv, reply_turn, thread, depth, position.

    position is the place within the conversation; thread, depth, conv_id and position give the reply order.
    """
    rows = parsed(messages.select("conv_id", "turn", "role", "text"))
    links = cut(linked(rows))
    best = F.max(F.when((F.col("level") == 1) & (F.col("to_conv") == F.col("conv_id")), F.col("to_turn")))
    far = F.min(F.when((F.col("level") == 1) & (F.col("to_conv") != F.col("conv_id")), F.struct("to_conv", "to_turn")))
    said = links.groupBy("conv_id", "turn").agg(F.count("*").alias("n_links"), best.alias("near"), far.alias("far"))
    numbered = row_numbers(rows, F.col("conv_id").asc_nulls_first(), F.col("turn").asc_nulls_first(), F.col("role").asc_nulls_first(), F.xxhash64("text"), name="row").withColumn("_conv", keyed(F.col("conv_id")))
    last = numbered.select((F.col("row") + 1).alias("row"), F.col("_conv").alias("_last_conv"), F.col("turn").alias("_last"))
    first = numbered.groupBy("_conv").agg(F.min("row").alias("_first"))
    out = numbered.join(last, "row", "left").join(first, "_conv").withColumn("position", F.col("row") - F.col("_first") + 1)
    out = out.withColumn("before", F.when((F.col("_last_conv") == F.col("_conv")) & (F.col("_last") < F.col("turn")), F.col("_last")))
    out = out.join(said, ["conv_id", "turn"], "left")
    ups = links.filter("level = 1 and to_conv <> conv_id").groupBy("conv_id").agg(F.min("to_conv").alias("up"))
    out = out.join(_threads(ups), "conv_id", "left")
    near, far = F.col("near"), F.when(F.col("near").isNull(), F.col("far"))
    back = near.isNull() & far.isNull() & F.col("before").isNotNull()
    return out.select(
        "conv_id", "turn", "role", F.col("own").alias("text"), F.size("quoted").cast("long").alias("n_quoted_lines"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
        F.when(near.isNotNull() | back, F.col("conv_id")).otherwise(far["to_conv"]).alias("reply_conv"), F.coalesce(near, far["to_turn"], F.when(back, F.col("before"))).alias("reply_turn"),
        F.coalesce("thread", "conv_id").alias("thread"), F.coalesce("depth", F.lit(0)).cast("long").alias("depth"), F.col("position").cast("long").alias("position"),
    )
