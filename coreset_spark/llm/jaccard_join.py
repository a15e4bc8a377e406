"""Exact n-gram Jaccard self-join by a partition of the universe, the pigeonhole principle and one-deletion neighbourhoods.

A document is the set of its distinct word n-grams. Two sets that link differ in few elements
for their size, so a hash that deals the elements to a little more segments than that leaves a
segment on which both agree, or differ by one element. Sets lie in bands of size; a band fixes
the number of segments, and a cost model decides how many of them are compared as they are and
how many with their one-deletion neighbourhoods, which count twice. Where all are compared as they
are, there are spare segments, and each set leaves out as many of its signatures: those that most
other sets share, by one order over all signatures, so that the rarest of those that two linked sets
share is never among them.

Equal sets are one class from the start. Classes that share a signature are candidates. Each
signature's least class is compared with the others first, where their parity sketches, which
give a lower bound of the difference, allow it; of three classes or fewer, all. What links falls together, and only signatures
of more whose classes still lie in different components are looked at again, in blocks: the largest component's
classes only against the others. Of the pairs that the sketches allow, each class sends its nearest ones to
verification, more in each turn, until none is left out; only signatures that left some out come to the next turn. Long documents have a second, longer sketch,
which pairs pass before their texts are fetched. So a large group of near copies costs few
pairs, and still every pair that could join two components is verified, on the words themselves. Texts
travel only for classes of pairs to verify.

Defined results: null, empty and wordless texts have no n-grams and link with nothing; fewer than
n words are one n-gram; rows with equal doc_id are rows of their own; a null doc_id takes part,
and comes before no other as a representative; an empty table gives an empty one; only doc_id and
text are read, whatever other columns are called.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache, lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, keyed
from .components import components


#: The last bits of a signature are the number of its band.
BANDS = 64


@dataclass(frozen=True)
class Join:
    """percent: 100 * |intersection| >= percent * |union| links. spread: of sizes within a band. block: rows of one side of a task's comparison. spare: share of signatures left out. broadcast_rows: the most keys of 16 bytes that are broadcast, and four times the most rows of two keys. keep_signatures: checkpoint them, at 8 bytes each, rather than make them
    again from the texts where they are read twice."""

    n: int = 5
    percent: int = 80
    spread: float = 1.6
    block: int = 1024
    spare: float = 0.08
    broadcast_rows: int = 2_000_000
    keep_signatures: bool = True

    def __post_init__(self) -> None:
        if len(edges(self.spread)) > BANDS:
            raise ValueError(f"a spread of {self.spread} makes more than {BANDS} bands")


# --- sets -------------------------------------------------------------------------------------

_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63], np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return x ^ (x >> np.uint64(33))


def words_of(text: str | None) -> list[bytes]:
    """Words between ASCII white space, with A-Z in lower case."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def grams_of(text: str | None, n: int) -> set[tuple[bytes, ...]]:
    w = words_of(text)
    return {tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


def hashed_set(text: str | None, n: int, seed: int = 0) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the n-grams."""
    w = words_of(text)
    if not w:
        return np.zeros(0, np.uint64)
    if len(w) < n:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(w), seed + 1)], np.uint64)
    digest = xxhash.xxh3_64_intdigest
    h = np.fromiter([digest(x, seed) for x in w], np.uint64, len(w))
    total = np.zeros(len(w) - n + 1, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(n):
            total += _mix(h[k : len(w) - n + 1 + k] * _ODD[k % 5] + np.uint64(k))
            total = total * np.uint64(3) if k + 1 < n else total
    return np.unique(_mix(total))


#: Binary logarithms of the most bits of a sketch and of a fine one, which sets have whose sketch would be longer.
#: Below that a sketch has FINENESS doublings more bits than elements. Half as many bits as elements tell unrelated sets apart,
#: several times as many also sets that miss the threshold by little.
COARSE, FINE, FINENESS = 13, 17, 1


def sketch_of(s: np.ndarray, most: int = COARSE) -> bytes:
    """Parities of the elements dealt to a power of two of bits: they differ in no more places than the sets."""
    bits = 1 << max(7, min(most, int(len(s)).bit_length() + FINENESS))
    return np.packbits((np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1).astype(np.uint8)).tobytes()


# --- bands and plans --------------------------------------------------------------------------


@cache
def edges(spread: float) -> list[int]:
    """Least sizes of the bands."""
    out = [1]
    while out[-1] < 2**40:
        out.append(max(out[-1] + 1, int(out[-1] * spread)))
    return out


def bands_of(size: int, j: Join) -> list[int]:
    """Bands whose sets may link with a set of this size that is no larger: its own, and those that start within reach."""
    e = edges(j.spread)
    k = bisect_right(e, size) - 1
    out = [k]
    while e[k + 1] * j.percent <= 100 * size:
        k += 1
        out.append(k)
    return out


def most_difference(a: int, b: int, percent: int) -> int:
    """The largest symmetric difference of two sets of these sizes that link."""
    return ((100 - percent) * (a + b)) // (100 + percent)


@dataclass(frozen=True)
class Plan:
    """single: segments compared as they are. double: segments with their one-deletion neighbourhoods. spare: signatures that a set leaves out."""

    single: int
    double: int
    spare: int

    @property
    def parts(self) -> int:
        return self.single + 2 * self.double


@cache
def plan(band: int, j: Join, sets: int) -> Plan | None:
    """The cheapest split of the difference that a band allows; None where only equal sets link.

    A signature costs one row. Unrelated sets meet where their subsets are small, so each
    segment adds the chance of that, times the number of sets.
    """
    top = edges(j.spread)[band + 1] - 1
    need = most_difference(top, top, j.percent) + 1
    if need == 1:
        return None
    best = None
    for double in range((need + 1) // 2 + 1) if need <= 64 else [0]:
        spare = math.ceil(need * j.spare) if double == 0 else 0
        single = max(0, need - 2 * double) + spare
        share = top / (single + 2 * double)
        rows = single + double + (2 * double * share)
        met = (0 if spare else single) * math.exp(-2 * share) + double * math.exp(-4 * share) * (1 + 4 * share)
        cost = rows + sets * met
        if best is None or cost < best[0]:
            best = (cost, Plan(single, double, spare))
    return best[1]


def spares(j: Join, sets: int) -> list[int]:
    """How many signatures a set leaves out in each band."""
    return [p.spare if (p := plan(band, j, sets)) else 0 for band in range(len(edges(j.spread)) - 1)]


def signatures(s: np.ndarray, j: Join, sets: int) -> np.ndarray:
    """Keys of the set's segments in each of its bands; their last bits are the band."""
    out = []
    with np.errstate(over="ignore"):
        for band in bands_of(len(s), j):
            p = plan(band, j, sets)
            if p is None:
                continue
            salt = np.uint64((band + 1) * 0x9E3779B97F4A7C15 % 2**64)
            part = ((_mix(s ^ salt) >> np.uint64(32)) * np.uint64(p.parts) >> np.uint64(32)).astype(np.int64)
            segment = np.where(part < 2 * p.double, part // 2, part - p.double)
            n = p.single + p.double
            order = np.argsort(segment, kind="stable")
            value = _mix(s + np.uint64(0x632BE59BD9B4E019))[order]
            size = np.bincount(segment, minlength=n)
            start = np.cumsum(size) - size
            run = np.concatenate([[np.uint64(0)], np.cumsum(value, dtype=np.uint64)])
            total = run[start + size] - run[start]
            name = salt + np.arange(n, dtype=np.uint64) * _ODD[1]
            ending = np.uint64(BANDS - 1)
            told = lambda x: (x & ~ending) | np.uint64(band)  # noqa: B023, E731
            out.append(told(_mix(_mix(total + size.astype(np.uint64)) + name)))
            if p.double:
                at = segment[order]
                some = at < p.double
                less = total[at[some]] - value[some] + (size[at[some]] - 1).astype(np.uint64)
                out.append(told(_mix(_mix(less) + name[at[some]])))
    return np.unique(np.concatenate(out)) if out else np.zeros(0, np.uint64)


# --- tasks ------------------------------------------------------------------------------------


def _classes(j: Join, sets: int, seed: int):
    """Per document: size, class (64 bits, and 64 more as a check), sketches and signatures; the last three once per class and task."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            size, cls, check, sketch, fine, sigs = [], [], [], [], [], []
            for text in batch.column(2).to_pylist():
                s = hashed_set(text, j.n, seed)
                size.append(len(s))
                if not len(s):
                    cls.append(None), check.append(None), sketch.append(None), fine.append(None), sigs.append(None)
                    continue
                d = xxhash.xxh3_128_intdigest(s.tobytes(), seed)
                c, k = (np.array([d & (2**64 - 1), d >> 64], np.uint64).view(np.int64)).tolist()
                cls.append(c), check.append(k)
                sketch.append(None if c in seen else sketch_of(s))
                fine.append(None if c in seen or len(s) < 1 << COARSE else sketch_of(s, FINE))
                sigs.append(None if c in seen or not j.keep_signatures else signatures(s, j, sets).view(np.int64))
                seen.add(c)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(size, pa.int64()), pa.array(cls, pa.int64()), pa.array(check, pa.int64()), pa.array(sketch, pa.binary()), pa.array(fine, pa.binary()), pa.array(sigs, pa.list_(pa.int64()))],
                names=["doc_id", "h", "n_shingles", "class", "check", "sketch", "fine", "sigs"],
            )

    return run


def _signed(j: Join, sets: int, seed: int):
    """(class, key) of each class once per task, from the texts."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                s = hashed_set(text, j.n, seed)
                c = int(np.array(xxhash.xxh3_128_intdigest(s.tobytes(), seed) & (2**64 - 1), np.uint64).view(np.int64)) if len(s) else None
                if c is None or c in seen:
                    continue
                seen.add(c)
                keys = signatures(s, j, sets).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), c)), pa.array(keys)], names=["class", "key"])

    return run


def _possible(j: Join):
    """Of pairs with their sizes and sketches, those that may link; a sketch that is null forbids nothing."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = []
            for n, m, x, y in zip(*(batch.column(i).to_pylist() for i in range(2, 6)), strict=True):
                if x is None or y is None:
                    ok.append(100 * min(n, m) >= j.percent * max(n, m))
                    continue
                bits = 8 * min(len(x), len(y))
                away = int(np.bitwise_count(_folded([x], bits) ^ _folded([y], bits)).sum())
                ok.append(100 * min(n, m) >= j.percent * max(n, m) and away <= most_difference(n, m, j.percent))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return run


def _verified(j: Join):
    """Of pairs with both texts, whether they link."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams = lru_cache(64)(lambda text: grams_of(text, j.n))
        for batch in batches:
            linked = []
            for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                x, y = grams(a), grams(b)
                both = len(x & y)
                linked.append(100 * both >= j.percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(linked, pa.bool_())], names=["a", "b", "linked"])

    return run


def _folded(sketches: list[bytes], bits: int) -> np.ndarray:
    out = np.zeros((len(sketches), bits // 64), np.uint64)
    for i, s in enumerate(sketches):
        x = np.frombuffer(s, np.uint64)
        out[i] = np.bitwise_xor.reduce(x.reshape(-1, bits // 64), 0)
    return out


def near_pairs(one: dict, two: dict, j: Join, most: int) -> tuple[np.ndarray, np.ndarray, bool]:
    """Places (in one, in two) of pairs of different components that the sizes and sketches allow: each row's ``most`` nearest; and whether any was left out."""
    bits = 8 * min(map(len, [*one["sketch"], *two["sketch"]]))
    x, y = _folded(one["sketch"], bits), _folded(two["sketch"], bits)
    n, m = np.asarray(one["size"], np.int64)[:, None], np.asarray(two["size"], np.int64)[None, :]
    away = np.zeros((x.shape[0], y.shape[0]), np.int64)
    for k in range(x.shape[1]):
        away += np.bitwise_count(x[:, k][:, None] ^ y[:, k][None, :])
    ok = (np.asarray(one["root"])[:, None] != np.asarray(two["root"])[None, :]) & (away <= ((100 - j.percent) * (n + m)) // (100 + j.percent))
    ok &= (100 * np.minimum(n, m) >= j.percent * np.maximum(n, m)) & (np.asarray(one["class"])[:, None] != np.asarray(two["class"])[None, :])
    if not ok.any():
        return np.zeros(0, np.int64), np.zeros(0, np.int64), False
    away[~ok] = 1 << 40
    keep = np.zeros_like(ok)
    for axis in (0, 1):
        if ok.shape[axis] <= most:
            keep |= ok
        else:
            cut_at = np.partition(away, most - 1, axis=axis).take([most - 1], axis=axis)
            rank = np.argsort(np.argsort(away, axis=axis, kind="stable"), axis=axis, kind="stable")
            keep |= (rank < most) & (away <= cut_at) & ok
    p, q = np.nonzero(keep)
    return p, q, bool((ok & ~keep).any())


def _open_pairs(j: Join, most: int):
    """Of rows sorted by (run, side): the near pairs within a run of one side, or between its two sides; more is the run's key where some were left out, else null."""
    names = ["class", "root", "size", "sketch"]

    def flush(key: tuple, sides: dict[int, dict]) -> pa.RecordBatch | None:
        one = sides.get(0)
        two = sides.get(1) if key[2] != key[1] else one
        if not one or not two:
            return None
        p, q, more = near_pairs(one, two, j, most)
        if not len(p):
            return None
        a, b = np.asarray(one["class"], np.int64)[p], np.asarray(two["class"], np.int64)[q]
        pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], 1), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), pa.array([key[0] if more else None] * len(pairs), pa.int64())], names=["a", "b", "more"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, sides = None, {}
        for batch in batches:
            columns = batch.to_pydict()
            for i, at in enumerate(zip(columns["key"], columns["i"], columns["j"], strict=True)):
                if at != key:
                    if key is not None and (out := flush(key, sides)):
                        yield out
                    key, sides = at, {}
                side = sides.setdefault(columns["side"][i], {n: [] for n in names})
                for n in names:
                    side[n].append(columns[n][i])
        if key is not None and (out := flush(key, sides)):
            yield out

    return run


# --- plans ------------------------------------------------------------------------------------


def _based(docs: DataFrame, j: Join, sets: int) -> tuple[DataFrame, DataFrame]:
    """Checkpointed documents with their classes, and the signatures (class, key); another seed where two different sets share a class."""
    rows = docs.select("doc_id", F.xxhash64("text").alias("h"), "text")
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, h long, n_shingles long, class long, check long, sketch binary, fine binary, sigs array<long>"
    for seed in range(100):
        base = cut(rows.mapInArrow(_classes(j, sets, 1000 * seed), schema))
        if base.groupBy("class").agg(F.min("check").alias("x"), F.max("check").alias("y")).filter("x <> y").isEmpty():
            if j.keep_signatures:
                return base, base.filter(F.col("sigs").isNotNull()).select("class", F.explode("sigs").alias("key"))
            return base, docs.select("text").mapInArrow(_signed(j, sets, 1000 * seed), "class long, key long")
    raise RuntimeError("classes collide under every seed")


def _members(keys: DataFrame, j: Join, sets: int) -> DataFrame:
    """(key, class, least, c) of every key that c classes, two at least, share and do not leave out, checkpointed.

    One aggregation finds the keys, and both members of those that two rows share. Only for keys of
    more rows are the signatures looked through once more: beside a broadcast of these keys while
    they are few, by a plain join beyond that. Each class then leaves out its most shared keys.
    """
    met = keys.groupBy("key").agg(F.min("class").alias("least"), F.max("class").alias("last"), F.count("*").alias("c"))
    met = cut(met.filter("least < last"))
    two = met.filter("c = 2").select("key", F.explode(F.array("least", "last")).alias("class"))
    many = met.filter("c > 2").select("key")
    small = many.count() <= j.broadcast_rows
    more = keys.join(F.broadcast(many) if small else many, "key").select("key", "class")
    shared = cut(two.unionByName(more.distinct()))
    counts = shared.groupBy("key").agg(F.count("*").alias("c"))
    band = F.col("key").bitwiseAND(BANDS - 1).cast("int")
    most_shared = Window.partitionBy("class", "band").orderBy(F.col("c").desc(), "key")
    ranked = shared.join(counts, "key").withColumn("band", band).withColumn("k", F.row_number().over(most_shared))
    left = cut(ranked.filter(F.col("k") > F.element_at(F.array(*map(F.lit, spares(j, sets))), F.col("band") + 1)).select("key", "class"))
    least = left.groupBy("key").agg(F.min("class").alias("least"), F.count("*").alias("c")).filter("c > 1")
    return cut(left.join(least, "key"))


#: Classes of a signature of which all pairs are looked at in the first turn.
ALL = 3


def _blocks(j: Join) -> dict[str, Column]:
    """own: a row's block among its key's; last: the last block that it meets, from 0. The classes of the largest component, main, lie in blocks of their own, behind the others', which alone they meet."""
    few, stray = F.col("c") <= j.block, F.col("root") != F.col("main.root")
    strays, mains = (F.ceil(x / j.block).cast("int") for x in (F.col("c") - F.col("main.n"), F.col("main.n")))
    deal = lambda n: F.pmod(F.xxhash64("class", F.lit(3)), n).cast("int")
    own = F.when(few, 0).when(stray, deal(strays)).otherwise(strays + deal(mains))
    return {"own": own, "last": F.when(few, 0).when(stray, strays + mains - 1).otherwise(strays - 1)}


def _linked_classes(docs: DataFrame, base: DataFrame, keys: DataFrame, j: Join, sets: int) -> DataFrame:
    """Links (u, v) between classes, enough to join every component."""
    known = base.filter(F.col("sketch").isNotNull())  # a row for each class and task
    row = F.min(F.struct(keyed(F.col("doc_id")).alias("id"), "h")).alias("row")
    facts = known.groupBy("class").agg(F.any_value("sketch").alias("sketch"), F.any_value("fine").alias("fine"), F.any_value("n_shingles").alias("size"), row)
    members = _members(keys, j, sets)
    needed = members.select("class").distinct()
    facts = cut(facts.join(needed, "class", "left_semi"))

    def beside(pairs: DataFrame, side: str, columns: DataFrame, names: dict[str, str]) -> DataFrame:
        return pairs.join(columns.select(F.col("class").alias(side), *[F.col(c).alias(n) for c, n in names.items()]), side)

    long = not facts.filter(F.col("fine").isNotNull()).isEmpty()

    def possible(pairs: DataFrame, sketch: str) -> DataFrame:
        if sketch == "fine" and not long:
            return pairs
        both = beside(beside(pairs, "a", facts, {"size": "n", sketch: "x"}), "b", facts, {"size": "m", sketch: "y"})
        return both.select("a", "b", "n", "m", "x", "y").mapInArrow(_possible(j), "a long, b long")

    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def near(run: DataFrame, most: int) -> DataFrame:
        """Distinct (a, b, more) of rows (key, i, j, side, class, root): what _open_pairs() tells of each run (key, i, j)."""
        met = run.join(facts.select("class", "size", "sketch"), "class").select("key", "i", "j", "side", "class", "root", "size", "sketch")
        met = met.repartition(parts, "key", "i", "j").sortWithinPartitions("key", "i", "j", "side")
        return cut(met.mapInArrow(_open_pairs(j, most), "a long, b long, more long").distinct())

    blocks, few, is_least = F.ceil(F.col("c") / j.block).cast("int"), F.col("c") <= ALL, F.col("class") == F.col("least")
    at = F.when(few, F.array(F.lit(0))).when(is_least, F.sequence(F.lit(0), blocks - 1)).otherwise(F.array(F.pmod(F.xxhash64("class", F.lit(3)), blocks).cast("int")))
    star = members.withColumn("i", F.explode(at)).withColumn("j", F.col("i") + F.when(few, 0).otherwise(1))  # two sides: the least class, and a block of the others
    star = star.select("key", "i", "j", F.when(few | is_least, 0).otherwise(1).alias("side"), "class", F.col("class").alias("root"))
    first = cut(possible(near(star, 1 << 40).select("a", "b"), "fine"))  # none is left out, so pairs are distinct

    def fetched(pairs: DataFrame) -> DataFrame:
        """One text of each class in the pairs; beside a broadcast of their rows' keys while these are few."""
        asked = pairs.select(F.explode(F.array("a", "b")).alias("class")).distinct()
        reps = cut(facts.select("class", "row.id", "row.h").join(asked, "class", "left_semi"))
        small = reps.count() <= j.broadcast_rows // 4
        texts = docs.select(keyed(F.col("doc_id")).alias("id"), F.xxhash64("text").alias("h"), "text").join(F.broadcast(reps) if small else reps, ["id", "h"])
        return cut(texts.groupBy("class").agg(F.any_value("text").alias("text")))  # rows may agree in id and text

    def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
        both = beside(beside(pairs, "a", texts, {"text": "x"}), "b", texts, {"text": "y"})
        return cut(both.select("a", "b", "x", "y").mapInArrow(_verified(j), "a long, b long, linked boolean"))

    texts = fetched(first)
    tried = verify(first, texts)
    links = tried.filter("linked").select(F.col("a").alias("u"), F.col("b").alias("v"))
    rows = members.filter(F.col("c") > ALL).select("key", "class")
    most = 2
    while True:
        roots = components(links)
        rooted = rows.join(roots.select(F.col("node").alias("class"), "root"), "class", "left").withColumn("root", F.coalesce("root", "class"))
        n = rooted.groupBy("key", "root").agg(F.count("*").alias("n"), F.expr("bit_xor(xxhash64(class))").alias("f0"), F.expr("bit_xor(xxhash64(class, 7))").alias("f1"))
        still = n.groupBy("key").agg(F.max(F.struct("n", "root")).alias("main"), F.sum("n").alias("c"), F.expr("bit_xor(f0)").alias("f0"), F.expr("bit_xor(f1)").alias("f1")).filter("c > main.n")
        still = still.groupBy("c", "f0", "f1").agg(F.min(F.struct("key", "main")).alias("one"))  # of keys with the same members, one
        live = cut(rooted.join(still.select("one.key", "c", "one.main"), "key"))
        run = live.withColumns(_blocks(j)).withColumn("other", F.explode(F.sequence(F.lit(0), "last")))
        run = run.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), F.when(F.col("own") <= F.col("other"), 0).otherwise(1).alias("side"), "class", "root")
        found = near(run, most)
        fresh = cut(possible(found.select("a", "b").distinct().join(tried.select("a", "b"), ["a", "b"], "left_anti"), "fine"))
        unread = fresh.select(F.explode(F.array("a", "b")).alias("class")).distinct().join(texts.select("class"), "class", "left_anti")
        if not unread.isEmpty():
            texts = texts.unionByName(fetched(unread.select(F.col("class").alias("a"), F.col("class").alias("b"))))
        new = verify(fresh, texts)
        again = cut(found.filter("more is not null").select(F.col("more").alias("key")).distinct())
        links = cut(links.unionByName(new.filter("linked").select(F.col("a").alias("u"), F.col("b").alias("v"))))
        if again.isEmpty():
            return links
        tried, rows, most = cut(tried.unionByName(new)), live.join(again, "key", "left_semi").select("key", "class"), most * 16


def _joined(docs: DataFrame, j: Join) -> DataFrame:
    """One row per row of docs: doc_id, h (hash of its text), n_shingles, component_id, and root, the component's own class: null for texts without words."""
    sets = docs.count()
    base, keys = _based(docs, j, sets)
    roots = components(_linked_classes(docs, base, keys, j, sets))
    least = base.filter(F.col("class").isNotNull()).groupBy("class").agg(F.min("doc_id").alias("least"))
    rooted = cut(least.join(roots.select(F.col("node").alias("class"), "root"), "class", "left").withColumn("root", F.coalesce("root", "class")))
    ids = rooted.select("class", "root").join(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("class", "root", "component_id")
    found = base.filter(F.col("class").isNotNull()).join(ids, "class").select("doc_id", "h", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), "root")
    wordless = base.filter(F.col("class").isNull())
    return found.unionByName(wordless.select("doc_id", "h", "n_shingles", F.col("doc_id").alias("component_id"), F.lit(None).cast("long").alias("root")))


def join(docs: DataFrame, j: Join = Join()) -> DataFrame:
    """One row per row of docs: doc_id, h (hash of its text), n_shingles, component_id."""
    return _joined(docs, j).drop("root")


def keep_one(docs: DataFrame, j: Join = Join()) -> DataFrame:
    """The rows of docs in their own columns: of each component one, the least by (doc_id, hash of the text), and all rows without words, which link with nothing."""
    found = _joined(docs, j).withColumn("_id", keyed(F.col("doc_id")))
    found = found.groupBy("_id", "h").agg(F.min("doc_id").alias("doc_id"), F.min("n_shingles").alias("n"), F.min("root").alias("root"), F.count("*").alias("c"))
    wordless = found.filter("n = 0").select("_id", F.col("h").alias("_h"), F.lit(1).cast("long").alias("c"))  # none of them is told apart
    first = found.filter("n > 0").groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no"), "doc_id", "h", "c")).alias("k0"))
    kept = cut(wordless.union(first.select(keyed(F.col("k0.doc_id")), F.col("k0.h"), F.col("k0.c"))))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), keyed(F.col("doc_id")).alias("_id"), F.xxhash64("text").alias("_h"))
    rows = rows.join(F.broadcast(kept) if kept.count() <= j.broadcast_rows // 4 else kept, ["_id", "_h"])
    out = rows.filter("c = 1").select("_row")
    if not kept.filter("c > 1").isEmpty():  # only rows that agree in doc_id and text are told apart by a window
        one = Window.partitionBy("_id", "_h").orderBy(F.lit(0))
        out = out.unionByName(rows.filter("c > 1").withColumn("_k", F.row_number().over(one)).filter("_k = 1").select("_row"))
    return out.select(*[F.col(f"_row.`{c}`").alias(c) for c in docs.columns])
