"""Mixing sources to target weights by pivotal dependent rounding.

Every document of a source should be taken ``target / source size`` times. The whole part is
sure; the fractions are rounded together. Two fractions meet, words move from one to the other
at random until one of them is 0 or 1, and the rest goes on to the next, so the expected words
of the pair never change. Documents of a source meet in hashed blocks, in order of size; each
block leaves at most one fraction, and these meet again in blocks of blocks, up a tree of
``log(documents) / log(block)`` levels. All of it is DataFrame functions, and no group is larger
than a block. Documents above a share of their source's target are rounded first, and the ratio
of the others makes up for what these took, so the error of a source is at most that share
where its other documents can make it up.

Defined results: null and empty texts have size 0; a null source is a source of its own, last in
order; rows that agree in doc_id, source and text are one unit that carries their joint number of
copies, spread as evenly as it goes; a source without words takes nothing; an empty table gives
an empty one; other columns are carried by :func:`mix` under their names, whatever these are.
Draws come from hashes of the seed and the unit, so reruns agree.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, keyed, words

#: Weights of the sources in code point order, repeating; the most that a text is repeated.
WEIGHTS, MOST = (5, 2, 1), 3
BLOCK = 64
LARGE = 0.01
TINY = 1e-9
#: Up to so many sources, of about 100 bytes each, their targets are broadcast; beyond that a plain join splits skewed sources.
BROADCAST_SOURCES = 100_000


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """From (source, source_size, n_units), each source's target: by weight, up to ``most`` times its size.

    The level of the fill is found in closed form: sources in order of cap over weight, each
    prefix of capped ones gives a level for the rest, and the first that no later cap undercuts
    holds. The window is over sources, one row each, not over documents.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    s = sizes.withColumn("_w", w).withColumn("_cap", F.col("source_size") * float(most))
    rising = Window.orderBy(F.col("_cap") / F.col("_w"), F.col("source").asc_nulls_last())
    before, every = rising.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    past = lambda c: F.coalesce(F.sum(c).over(before), F.lit(0.0))
    s = s.withColumn("_level", (F.sum("source_size").over(every) - past("_cap")) / (F.sum("_w").over(every) - past("_w")))
    s = s.withColumn("_level", F.max(F.when(F.col("_level") * F.col("_w") <= F.col("_cap"), F.col("_level"))).over(every))
    return s.select("source", "source_size", "n_units", F.least("_cap", F.coalesce("_level", F.lit(0.0)) * F.col("_w")).alias("target"))


def _uniform(*parts: Column) -> Column:
    return F.call_function("shiftrightunsigned", F.xxhash64(*parts), F.lit(11)).cast("double") * float(2**-53)


def _meet(items: Column) -> Column:
    """Folds sorted (size, unit, p, u): the units that reach 1, and the last one, whose p may be 0 or 1 by now."""
    first = F.element_at(items, 1)
    start = F.struct(first["size"].alias("size"), first["unit"].alias("unit"), first["p"].alias("p"), F.slice(F.transform(items, lambda x: x["unit"]), 1, 0).alias("won"))

    def step(a: Column, x: Column) -> Column:
        up = F.least((1 - a["p"]) * a["size"], x["p"] * x["size"])  # words that a may take from x
        down = F.least(a["p"] * a["size"], (1 - x["p"]) * x["size"])
        moved = F.when(x["u"] * (up + down) < down, up).otherwise(-down)
        p, q = a["p"] + moved / a["size"], x["p"] - moved / x["size"]
        keep = (p > TINY) & (p < 1 - TINY)  # a is still a fraction
        done = F.when(keep, F.struct(x["unit"].alias("unit"), q.alias("p"))).otherwise(F.struct(a["unit"].alias("unit"), p.alias("p")))
        return F.struct(
            F.when(keep, a["size"]).otherwise(x["size"]).alias("size"),
            F.when(keep, a["unit"]).otherwise(x["unit"]).alias("unit"),
            F.when(keep, p).otherwise(q).alias("p"),
            F.when(done["p"] > 0.5, F.concat(a["won"], F.array(done["unit"]))).otherwise(a["won"]).alias("won"),
        )

    return F.aggregate(F.slice(items, 2, F.size(items)), start, step)


def _rounds(n: int, block: int) -> int:
    return max(1, math.ceil(math.log(max(n, 2)) / math.log(block) - 1e-9))


def pivotal(items: DataFrame, seed: int = 0, block: int = BLOCK) -> DataFrame:
    """The winners (group, unit) among (group, n, unit, size, p): a group's sum of p * size moves by one size at most.

    n: a bound on the number of units of the group; 0 < p < 1 and size > 0.
    """
    level = items.select("group", "unit", "size", "p", F.ceil(F.col("n") / block).alias("blocks"))
    level = level.withColumn("block", F.pmod(F.xxhash64("unit", F.lit(seed)), F.col("blocks")))
    most = items.agg(F.max("n")).first()[0] or 0
    won = None
    for turn in range(_rounds(most, block)):
        last = turn == _rounds(most, block) - 1
        item = F.struct("size", "unit", "p", _uniform(F.col("unit"), F.lit(seed), F.lit(turn)).alias("u"))
        met = level.groupBy("group", "block").agg(F.max("blocks").alias("blocks"), _meet(F.sort_array(F.collect_list(item))).alias("m"))
        met = cut(met.select("group", "block", "blocks", "m.*"))
        some = met.select("group", F.explode("won").alias("unit"))
        some = some.unionByName(met.filter(F.col("p") >= 1 - TINY).select("group", "unit"))
        left = met.filter(F.col("p").between(TINY, 1 - TINY))
        if last:
            some = some.unionByName(left.filter(_uniform(F.col("unit"), F.lit(seed), F.lit(-1)) < F.col("p")).select("group", "unit"))
        won = some if won is None else won.unionByName(some)
        level = left.select("group", "unit", "size", "p", F.ceil(F.col("blocks") / block).alias("blocks"), F.floor(F.col("block") / block).alias("block"))
    return won


def _sized(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "source", F.xxhash64("text").alias("h"), F.size(words(F.col("text"))).cast("long").alias("size"))


def _shares(sized: DataFrame, weights: tuple[int, ...], most: int, seed: int, block: int, large: float = LARGE) -> DataFrame:
    """Per unit: its source's size and target, its number of rows, and the copies that all of them get."""
    units = sized.groupBy("doc_id", "source", "h", "size").agg(F.count("*").alias("rows"))
    by_source = units.groupBy("source").agg(F.sum(F.col("size") * F.col("rows")).alias("source_size"), F.count("*").alias("n_units"))
    goal = targets(by_source, weights, most)
    goal = cut(goal.withColumn("group", keyed(F.col("source"))).drop("source"))
    few = goal.count() <= BROADCAST_SOURCES
    units = units.withColumn("group", keyed(F.col("source"))).join(F.broadcast(goal) if few else goal, "group")
    units = cut(units.withColumn("unit", F.struct("doc_id", "h")).withColumn("large", (F.col("size") > F.col("target") * large) & (F.col("size") > 0)))
    some = _copies(units.filter("large"), F.try_divide("target", "source_size"), most, seed, block)
    took = some.groupBy("group").agg(F.sum(F.col("size") * F.col("copies")).alias("took"), F.sum(F.col("size") * F.col("rows")).alias("of"))
    rest = units.filter("not large").join(F.broadcast(took) if few else took, "group", "left")
    ratio = F.try_divide(F.col("target") - F.coalesce("took", F.lit(0)), F.col("source_size") - F.coalesce("of", F.lit(0)))
    return some.unionByName(_copies(rest, ratio, most, seed + 1, block))


def _copies(units: DataFrame, ratio: Column, most: int, seed: int, block: int) -> DataFrame:
    """The units' rounded copies, of all their rows together."""
    mass = F.least(F.greatest(F.coalesce(ratio, F.lit(0.0)), F.lit(0.0)), F.lit(float(most))) * F.col("rows")
    units = units.withColumn("whole", F.floor(mass + TINY)).withColumn("p", mass - F.col("whole"))
    live = units.filter((F.col("p") > TINY) & (F.col("size") > 0))
    won = pivotal(live.select("group", F.col("n_units").alias("n"), "unit", "size", "p"), seed, block)
    won = won.select("group", keyed(F.col("unit.doc_id")).alias("_id"), F.col("unit.h").alias("h"), F.lit(1).alias("one"))
    copies = F.col("whole") + F.coalesce("one", F.lit(0))
    return units.withColumn("_id", keyed(F.col("doc_id"))).join(won, ["group", "_id", "h"], "left").select("group", "_id", "h", "size", "source_size", "target", "rows", copies.alias("copies"))


def _spread(docs: DataFrame, shares: DataFrame) -> DataFrame:
    """Each row of docs (with _group, _id and _h) beside its unit's share, and its own copies in _copies."""
    same = Window.partitionBy("_group", "_id", "_h").orderBy(F.lit(0))
    rows = docs.withColumn("_k", F.row_number().over(same))
    s = shares.select(F.col("group").alias("_group"), "_id", F.col("h").alias("_h"), F.col("size").alias("_size"), F.col("source_size").alias("_source_size"), F.col("target").alias("_target"), F.col("rows").alias("_rows"), F.col("copies").alias("_all"))
    own = F.floor(F.col("_all") / F.col("_rows")) + F.when(F.col("_k") <= F.col("_all") % F.col("_rows"), 1).otherwise(0)
    return rows.join(s, ["_group", "_id", "_h"]).withColumn("_copies", own.cast("int"))


def measure(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST, seed: int = 0, block: int = BLOCK) -> DataFrame:
    """One row per row of docs: doc_id, size, source_size, target and taken, the words that the mix takes."""
    sized = cut(_sized(docs))
    shares = _shares(sized, weights, most, seed, block)
    rows = sized.select("doc_id", keyed(F.col("source")).alias("_group"), keyed(F.col("doc_id")).alias("_id"), F.col("h").alias("_h"))
    out = _spread(rows, shares)
    return out.select("doc_id", F.col("_size").alias("size"), F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), (F.col("_size") * F.col("_copies")).alias("taken"))


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST, seed: int = 0, block: int = BLOCK) -> DataFrame:
    """The rows of docs, each as often as the mix takes it."""
    shares = _shares(cut(_sized(docs)), weights, most, seed, block)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), keyed(F.col("source")).alias("_group"), keyed(F.col("doc_id")).alias("_id"), F.xxhash64("text").alias("_h"))
    out = _spread(rows, shares).filter("_copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies"))))
    return out.select(*[F.col(f"_row.`{c}`").alias(c) for c in docs.columns])
