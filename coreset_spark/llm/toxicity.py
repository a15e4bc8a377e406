"""Toxicity by a counterfactual-regularised classifier.

Logistic regression over the distinct words of a text and over their beginnings, so that inflected
and compound forms count together. Both are chosen by how strongly they go with the label,
counted over the sample; identity terms are always among them. Of every sampled
text that names a group, copies name other groups of the same kind instead, and the change of
score between a text and its copies is penalised, so that naming a group neither makes a text
toxic nor harmless.

The fit sees a bounded sample (``sample`` labelled rows that are not held out, drawn by hash);
scoring is one pass over all texts, whole, and shuffles nothing.

Defined results: null and empty texts get the score of a text without known words; labels that
are null, or of ids that documents lack, are ignored; several labels of one id count as the
largest; rows with equal doc_id are scored each by its text; without usable labels every score is
one half; a text is its set of words, however long it is; an empty table gives an empty one; only doc_id and text are read.

The identity terms are a parameter: ``Toxicity(identities={kind: (term, ...)})`` takes one's own.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut
from .fitting import Rows, held_out, logistic, sampled

# Words that name groups of people, by language and kind; a swap stays within both.
IDENTITIES = {
    "en gender": ("man", "woman", "men", "women", "male", "female", "boy", "girl", "transgender"),
    "en religion": ("christian", "muslim", "jewish", "hindu", "buddhist", "atheist", "catholic", "sikh"),
    "en origin": ("african", "asian", "european", "american", "mexican", "arab", "indian", "chinese", "black", "white", "latino"),
    "en orientation": ("gay", "lesbian", "straight", "bisexual", "queer", "heterosexual"),
    "en ability": ("disabled", "blind", "deaf", "autistic"),
    "en age": ("old", "young", "elderly", "teenage"),
    "de gender": ("mann", "frau", "männer", "frauen", "männlich", "weiblich", "junge", "mädchen"),
    "de religion": ("christ", "muslimin", "moslem", "jude", "jüdin", "katholik", "protestant", "atheistin"),
    "de origin": ("deutscher", "türke", "pole", "russe", "afrikaner", "asiate", "araber", "inder", "syrer"),
    "de orientation": ("schwul", "lesbisch", "heterosexuell", "bisexuell"),
    "de ability": ("behindert", "gehörlos", "autistisch"),
    "es gender": ("hombre", "mujer", "hombres", "mujeres", "chico", "chica", "niño", "niña"),
    "es religion": ("cristiano", "musulmán", "judío", "hindú", "budista", "ateo", "católico"),
    "es origin": ("español", "mexicano", "africano", "asiático", "árabe", "gitano", "chino", "colombiano"),
    "es orientation": ("lesbiana", "heterosexual", "bisexual", "homosexual"),
    "es ability": ("discapacitado", "ciego", "sordo", "autista"),
    "fr gender": ("homme", "femme", "hommes", "femmes", "garçon", "fille"),
    "fr religion": ("chrétien", "musulman", "juif", "hindou", "bouddhiste", "athée", "catholique"),
    "fr origin": ("français", "africain", "asiatique", "arabe", "chinois", "algérien", "marocain", "polonais"),
    "fr orientation": ("homosexuel", "lesbienne", "hétérosexuel", "bisexuel"),
    "fr ability": ("handicapé", "aveugle", "sourd"),
}


@dataclass(frozen=True)
class Toxicity:
    """sample: labelled rows of the fit, at most about. features: words that are kept. swaps: copies of a text that names a group."""

    sample: int = 12_000
    features: int = 4_000
    least: int = 3
    l2: float = 5e-5
    steps: int = 400
    penalty: float = 1.0
    swaps: int = 2
    seed: int = 0
    identities: dict = field(default_factory=lambda: IDENTITIES, hash=False, compare=False)


_WORD = re.compile(r"\w+")
BEGIN = (4, 8)


def tokens(text: str | None) -> set[str]:
    return set(_WORD.findall(text.lower())) if text else set()


def features(words: set[str]) -> dict[str, int]:
    """The words, once each, and their beginnings of 4 to 8 letters with the number of longer words that have them."""
    out = Counter(w[:k] + "*" for w in words for k in range(BEGIN[0], min(BEGIN[1] + 1, len(w))))
    out.update(dict.fromkeys(words, 1))
    return out


def swapped(words: set[str], t: Toxicity) -> list[set[str]]:
    """Copies in which every group is replaced by the next ones of its kind."""
    kinds = {w: (kind, i) for kind, terms in t.identities.items() for i, w in enumerate(terms)}
    named = [w for w in words if w in kinds]
    out = []
    for turn in range(1, t.swaps + 1) if named else []:
        copy = set(words)
        for w in named:
            terms = t.identities[kinds[w][0]]
            copy.discard(w)
            copy.add(terms[(kinds[w][1] + turn) % len(terms)])
        out.append(copy)
    return out


@dataclass
class Model:
    weights: dict[str, float]
    bias: float

    def score(self, text: str | None) -> float:
        z, w = self.bias, self.weights
        words = tokens(text)
        for x in words & w.keys():
            z += w[x]
        counts = Counter(b for x in words for k in range(BEGIN[0], min(BEGIN[1] + 1, len(x))) if (b := x[:k] + "*") in w)
        for b, n in counts.items():
            z += w[b] * math.log2(1 + n)
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per task and word, the number of toxic and of other texts that have it."""
    seen = (Counter(), Counter())
    for batch in batches:
        for y, words in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            seen[1 if y else 0].update(features(set(words)).keys())
    words = list(seen[0].keys() | seen[1].keys())
    for k in range(0, len(words), 50_000):
        part = words[k : k + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([seen[1][w] for w in part], pa.int64()), pa.array([seen[0][w] for w in part], pa.int64())], names=["word", "n1", "n0"])


def _tokenised(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([sorted(tokens(x)) for x in batch.column(1).to_pylist()], pa.list_(pa.string()))], names=["y", "words"])


def fit(docs: DataFrame, labels: DataFrame, t: Toxicity = Toxicity(), label: str = "toxic") -> Model:
    """Fits on the bounded sample: word counts are grouped in Spark, the chosen columns of the sample come to the driver."""
    drawn = sampled(labels, label, t.sample, t.seed)
    rows = cut(docs.select("doc_id", "text").join(drawn, "doc_id").select("y", "text").mapInArrow(_tokenised, "y int, words array<string>"))
    n1, n0 = rows.agg(F.coalesce(F.sum("y"), F.lit(0)), F.count("*") - F.coalesce(F.sum("y"), F.lit(0))).first()
    if not n1 or not n0:
        return Model({}, 0.0)
    counts = rows.mapInArrow(_counted, "word string, n1 long, n0 long").groupBy("word").agg(F.sum("n1").alias("n1"), F.sum("n0").alias("n0"))
    odds = lambda n, of: F.log((n + 0.5) / (F.lit(of) - n + 0.5))
    z = (odds(F.col("n1"), n1) - odds(F.col("n0"), n0)) / F.sqrt(1 / (F.col("n1") + 0.5) + 1 / (F.col("n0") + 0.5))
    best = counts.filter(F.col("n1") + F.col("n0") >= t.least).orderBy(F.abs(z).desc(), "word").limit(t.features)
    names = {w for terms in t.identities.values() for w in terms}
    vocabulary = sorted({r["word"] for r in best.select("word").collect()} | names)
    at = {w: i for i, w in enumerate(vocabulary)}

    def weigh(words: set[str]) -> list[tuple[int, float]]:
        return [(at[f], math.log2(1 + n)) for f, n in features(words).items() if f in at]

    def chosen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Per text: its label, its columns and values, and the same of the difference to each of its copies, as bytes."""
        for batch in batches:
            own = [set(x) for x in batch.column(1).to_pylist()]
            lists = [[weigh(x), *([*weigh(x), *((i, -v) for i, v in weigh(c))] for c in swapped(x, t))] for x in own]
            flat = [[p for part in x for p in part] for x in lists]
            packed = [np.array([p[k] for p in x], kind).tobytes() for k, kind in ((0, "<i4"), (1, "<f4")) for x in flat]
            sizes = [np.array([len(part) for part in x], "<i4").tobytes() for x in lists]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.binary()) for c in (sizes, packed[: len(own)], packed[len(own) :]))], names=["y", "sizes", "at", "value"])

    sample = rows.mapInArrow(chosen, "y int, sizes binary, at binary, value binary").toPandas()
    y = sample["y"].to_numpy(np.float64)
    sizes = [np.frombuffer(x, "<i4") for x in sample["sizes"]]
    every, own = np.concatenate(sizes), np.concatenate([np.arange(len(x)) == 0 for x in sizes])
    index, value = (np.frombuffer(b"".join(sample[c]), kind) for c, kind in (("at", "<i4"), ("value", "<f4")))
    mine = np.repeat(own, every)

    def part(rows_of: np.ndarray, cells: np.ndarray) -> Rows:
        n = int(rows_of.sum())
        return Rows(index[cells].astype(np.int64), value[cells].astype(np.float64), np.repeat(np.arange(n), every[rows_of]), n)

    w, b = logistic(part(own, mine), y, len(vocabulary), t.l2, part(~own, ~mine), t.penalty, t.steps)
    return Model({v: float(w[i]) for v, i in at.items() if w[i]}, b)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score and predicted of every row."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = [model.score(x) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(scores, pa.float64()), pa.array([int(s >= 0.5) for s in scores], pa.int32())], names=["doc_id", "held_out", "score", "predicted"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, f"doc_id {kind}, held_out boolean, score double, predicted int")
