"""Best-fit packing of tokenised documents into sequences, by hierarchical residual packing.

A task tokenises its documents and packs their pieces best-fit; full and nearly full bins are
final. The bins with room go on as items of their own, a few partitions' bins meet in one group
on the next level, and are packed best-fit again, up a tree whose root sees the last of them.

Bins of one fill are interchangeable, so a group is told how many there are of each, at most as
many numbers as a sequence has places, and packs the numbers: what comes out are kinds of bins,
each with a count. Bins know their place among those of their fill, from which their place in a
bin of a kind is worked out afterwards. So a group's size is bounded, whatever the input, and every bin
with room goes all the way up.

Defined results: a null or empty text is the closing id alone; equal rows are packed each by
itself; a text longer than a sequence is cut into whole sequences and a shorter rest; an empty
table gives an empty one; only doc_id and text are read, whatever other columns are called.
"""

from __future__ import annotations

import math
import re
import zlib
from bisect import bisect_right
from collections import defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import cut


@dataclass(frozen=True)
class Packing:
    """tokenizer: a file's place, read by each worker. nearly_full: the fill from which a bin is final."""

    tokenizer: str
    capacity: int = 2048
    close_with: int = 0
    nearly_full: float = 0.995
    fan: int = 8
    cache: int = 800_000


class WordIds:
    """Ids of texts as little-endian 32-bit bytes.

    The tokenizer drops white space and never merges across it, so words are encoded once and
    kept. New words are encoded together: words of letters alone, each of which ends with the one
    token that ends a word, as one text; others with a special token between them; words that may
    hold such a token, and texts with characters that Python alone takes for white space, by
    themselves.
    """

    def __init__(self, path: str, most: int) -> None:
        from tokenizers import Tokenizer

        self.tokenizer, self.most, self.known = Tokenizer.from_file(path), most, {}
        special = {i: t.content for i, t in self.tokenizer.get_added_tokens_decoder().items() if t.special}
        self.between, self.mark = max(special.items(), default=(None, None))
        self.odd = re.compile("|".join(map(re.escape, special.values())) or "(?!)", re.IGNORECASE)

        suffix = getattr(self.tokenizer.model, "end_of_word_suffix", None)
        size = self.tokenizer.get_vocab_size()
        self.last = np.array([bool(suffix) and (self.tokenizer.id_to_token(i) or "").endswith(suffix) for i in range(size)])

    def _each(self, texts: list[str]) -> list[bytes]:
        return [np.asarray(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _together(self, words: list[str], text: str, ends) -> None:
        """Encodes a text that holds the words in order; ends finds, in its ids, the end of each and the start of the next."""
        ids = np.asarray(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")
        stop, start = ends(ids)
        if len(stop) != len(words):
            raise ValueError("the tokenizer does not keep words apart")
        data = ids.tobytes()
        for w, i, j in zip(words, (4 * start).tolist(), (4 * stop).tolist(), strict=True):
            self.known[w] = data[i:j]

    def _learn(self, new: list[str]) -> None:
        plain, marked, alone, suffixed = [], [], [], bool(self.last.any())
        for w in new:
            (plain if suffixed and w.isalpha() else marked if self.mark and not self.odd.search(w) else alone).append(w)
        self.known.update(zip(alone, self._each(alone), strict=True))

        def by_mark(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            at = np.flatnonzero(ids == self.between)
            return np.append(at, len(ids)), np.append(0, at + 1)

        def by_suffix(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            at = np.flatnonzero(self.last[ids]) + 1
            return at, np.append(0, at[:-1])

        for words, between, ends in ((plain, " ", by_suffix), (marked, f" {self.mark} ", by_mark)):
            for k in range(0, len(words), 2_000):
                self._together(words[k : k + 2_000], between.join(words[k : k + 2_000]), ends)

    def __call__(self, texts: list[str]) -> list[bytes]:
        split = [None if re.search("[\x1c-\x1f]", t) else t.split() for t in texts]
        if len(self.known) > self.most:
            self.known.clear()
        new: set[str] = set()
        for words in split:
            new.update(words or ())
        if new := new.difference(self.known):
            self._learn(list(new))
        get = self.known.__getitem__
        return [self._each([t])[0] if words is None else b"".join(map(get, words)) for t, words in zip(texts, split, strict=True)]


def _runs(texts: list[str | None], chars: int = 2_000_000) -> Iterator[list[str]]:
    """Consecutive texts of about so many characters together."""
    some, size = [], 0
    for t in texts:
        some.append(t or "")
        size += len(some[-1])
        if size >= chars:
            yield some
            some, size = [], 0
    if some:
        yield some


_loaded: dict[tuple, WordIds] = {}


def _ids(path: str, most: int) -> WordIds:
    if (path, most) not in _loaded:
        _loaded[path, most] = WordIds(path, most)
    return _loaded[path, most]


def best_fit(lengths: Iterable[int], capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-fit decreasing: of each item its bin and its offset, and of each bin its fill.

    Bins with equal room are interchangeable, so they lie on one pile per room, and a bit mask
    of the piles that are not empty finds the tightest one that fits.
    """
    lengths = np.asarray(lengths, dtype=np.int64)
    order = np.argsort(-lengths, kind="stable")
    place, offset = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    piles: dict[int, list[int]] = defaultdict(list)
    mask, room = 0, []
    for i in order.tolist():
        n = int(lengths[i])
        fits = mask >> n
        if fits:
            r = n + (fits & -fits).bit_length() - 1
            b = piles[r].pop()
            if not piles[r]:
                mask &= ~(1 << r)
        else:
            r, b = capacity, len(room)
            room.append(capacity)
        place[i], offset[i], room[b] = b, capacity - r, r - n
        if r - n:
            piles[r - n].append(b)
            mask |= 1 << (r - n)
    return place, offset, capacity - np.asarray(room, np.int64)


@dataclass
class Kind:
    """count bins alike: room, and items of one fill each: (fill, how many in a bin, where they begin)."""

    count: int
    room: int
    items: list[tuple[int, int, int]]


def best_fit_counts(counts: dict[int, int], capacity: int) -> list[Kind]:
    """Best-fit decreasing of so many items of each length, as best_fit() packs them one by one: an item's like goes beside it while there is room."""
    kinds: list[Kind] = []
    piles: dict[int, list[Kind]] = defaultdict(list)
    mask = 0

    def add(kind: Kind) -> None:
        nonlocal mask
        if kind.room:
            piles[kind.room].append(kind)
            mask |= 1 << kind.room
        kinds.append(kind)

    for n in sorted(counts, reverse=True):
        left = counts[n]
        while left:
            fits = mask >> n
            room = n + (fits & -fits).bit_length() - 1 if fits else capacity
            each = min(room // n, left)
            if not fits:
                add(Kind(left // each, room - each * n, [(n, each, 0)]))
                left %= each
                continue
            pile = piles[room]
            old = pile[-1]
            some = min(old.count, left // each)
            left -= some * each
            old.count -= some
            if not old.count:
                pile.pop()
                if not pile:
                    mask &= ~(1 << room)
            add(Kind(some, room - each * n, [*old.items, (n, each, capacity - room)]))
    return [k for k in kinds if k.count]


def _packed(batches: Iterable[pa.RecordBatch], p: Packing, id_type: pa.DataType) -> Iterator[dict]:
    """Of one partition: its pieces, each with its bin in the partition, its offset, and the bin's fill and finality."""
    encode = _ids(p.tokenizer, p.cache)
    close = np.asarray([p.close_with], "<u4").tobytes()
    ids, piece, start, length, crc = [], [], [], [], []
    for batch in batches:
        encoded = (data for some in _runs(batch.column(1).to_pylist()) for data in encode(some))
        for doc_id, data in zip(batch.column(0).to_pylist(), encoded, strict=True):
            data += close
            for k in range(0, len(data), 4 * p.capacity):
                part = data[k : k + 4 * p.capacity]
                ids.append(doc_id)
                piece.append(k // (4 * p.capacity))
                start.append(k // 4)
                length.append(len(part) // 4)
                crc.append(zlib.crc32(part))
    place, offset, fill = best_fit(length, p.capacity)
    final = fill >= p.capacity * p.nearly_full
    among = np.zeros(len(fill), np.int64)  # place of an open bin among those of its fill
    order = np.flatnonzero(~final)[np.argsort(fill[~final], kind="stable")]
    first = np.searchsorted(fill[order], fill[order])
    among[order] = np.arange(len(order)) - first
    yield {
        "doc_id": pa.array(ids, id_type), "piece": pa.array(piece, pa.int32()), "start": pa.array(start, pa.int64()), "length": pa.array(length, pa.int64()),
        "ids_crc32": pa.array(crc, pa.int64()), "bin": pa.array(place), "offset": pa.array(offset), "fill": pa.array(fill[place]), "among": pa.array(among[place]), "final": pa.array(final[place]),
    }


def pieces(docs: DataFrame, p: Packing) -> DataFrame:
    """One row per piece, with the task's partition and bin; tokenised and packed within the partition."""
    kind = docs.schema["doc_id"].dataType
    schema = T.StructType([T.StructField("doc_id", kind), T.StructField("piece", T.IntegerType()), *[T.StructField(c, T.LongType()) for c in ("start", "length", "ids_crc32", "bin", "offset", "fill", "among")], T.StructField("final", T.BooleanType())])
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for columns in _packed(batches, p, arrow.field("doc_id").type):
            table = pa.table(columns, schema=arrow)
            yield from table.to_batches(max_chunksize=10_000)

    return docs.select("doc_id", "text").mapInArrow(run, schema).withColumn("part", F.spark_partition_id().cast("long"))


#: A row says what becomes of the bins of one fill of one group below, or (below null) how many open bins of a fill there are now.
MERGED = "at long, below long, fill long, n long, shift long, runs array<struct<begin:long,each:long,offset:long,bin:long,fill:long,among:long,final:boolean>>"


def _merge(p: Packing):
    """Packs the numbers (at, fill, n) of the groups below that meet in one."""
    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["fill", "at"], kind="stable")
        kinds = best_fit_counts(rows.groupby("fill")["n"].sum().to_dict(), p.capacity)
        used: dict[int, int] = defaultdict(int)  # of a fill, the items that have a place
        runs: dict[int, list[tuple]] = defaultdict(list)
        still: dict[int, int] = defaultdict(int)
        bins = 0
        for kind in kinds:
            fill = p.capacity - kind.room
            final = fill >= p.capacity * p.nearly_full
            for n, each, offset in kind.items:
                runs[n].append((used[n], each, offset, bins, fill, still[fill], final))
                used[n] += kind.count * each
            bins += kind.count
            if not final:
                still[fill] += kind.count
        out, shift = [], defaultdict(int)
        for at, fill, n in zip(rows["at"].tolist(), rows["fill"].tolist(), rows["n"].tolist(), strict=True):
            begin, mine = shift[fill], runs[fill]
            places = [r[0] for r in mine]
            low, high = bisect_right(places, begin) - 1, bisect_right(places, begin + n - 1)
            shift[fill] += n
            out.append((key[0], at, fill, n, begin, mine[low:high]))
        out += [(key[0], None, fill, n, 0, []) for fill, n in still.items()]
        names = ["begin", "each", "offset", "bin", "fill", "among", "final"]
        frame = pd.DataFrame([(*r[:5], [dict(zip(names, x, strict=True)) for x in r[5]]) for r in out], columns=["at", "below", "fill", "n", "shift", "runs"])
        return frame.astype({"below": "Int64"})

    return run


#: Rows of a level's numbers that are broadcast.
FEW = 200_000


def pack(docs: DataFrame, p: Packing) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    The lowest level's rows are checkpointed: what is packed on the way up is read once more at
    the end, and must be the same then. Each level joins the open bins, not the pieces, to its numbers, and the pieces
    are joined once at the end.
    """
    base = cut(pieces(docs, p))
    parts = (base.agg(F.max("part")).first()[0] or 0) + 1
    levels = max(0, math.ceil(math.log(parts, p.fan) - 1e-9))
    state = ["part", "own_bin", "level", "at", "bin", "offset", "fill", "among", "final"]
    rows = base.filter("not final").select("part", F.col("bin").alias("own_bin"), F.lit(0).alias("level"), F.col("part").alias("at"), "bin", F.lit(0).cast("long").alias("offset"), "fill", "among", "final").distinct()
    counts = rows.groupBy("at", "fill").agg(F.count("*").alias("n"))
    moved = None
    for level in range(1, levels + 1):
        merged = cut(counts.withColumn("group", F.floor(F.col("at") / p.fan)).groupBy("group").applyInPandas(_merge(p), MERGED))
        told = merged.filter("below is not null").select(F.col("at").alias("up"), F.col("below").alias("at"), "fill", "shift", "runs")
        told = F.broadcast(told) if told.count() <= FEW else told
        now = rows if moved is None else moved.filter("not final")
        step = now.join(told, ["at", "fill"]).withColumn("g", F.col("shift") + F.col("among"))
        step = step.withColumn("r", F.element_at(F.filter("runs", lambda r: r["begin"] <= F.col("g")), -1)).withColumn("i", F.col("g") - F.col("r.begin"))
        nth = F.floor(F.col("i") / F.col("r.each"))
        new = step.select(
            "part", "own_bin", F.lit(level).alias("level"), F.col("up").alias("at"), (F.col("r.bin") + nth).alias("bin"), (F.col("offset") + F.col("r.offset") + F.col("i") % F.col("r.each") * F.col("fill")).alias("offset"),
            F.col("r.fill").alias("fill"), (F.col("r.among") + nth).alias("among"), F.col("r.final").alias("final"),
        )
        moved = cut(new if moved is None else new.unionByName(moved.filter("final")))
        counts = merged.filter("below is null").select("at", "fill", "n")
    rows = rows if moved is None else moved
    rows = rows.select("part", F.col("own_bin").alias("bin"), "level", "at", F.col("bin").alias("at_bin"), F.col("offset").alias("at_offset"))
    out = base.join(rows, ["part", "bin"], "left")
    level, at, at_bin = F.coalesce("level", F.lit(0)), F.coalesce("at", "part"), F.coalesce("at_bin", "bin")
    # part * 16 + level and the bin, in one number: a group's bins stay below 2^31, 16 levels are 8^16 partitions
    number = F.call_function("shiftleft", at * 16 + level, F.lit(31)) + at_bin
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", number.alias("sequence_id"), (F.col("offset") + F.coalesce("at_offset", F.lit(0))).alias("offset"))
