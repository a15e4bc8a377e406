"""Quality by hierarchical empirical Bayes: a document's own evidence, combined with its host's and its path's.

A classifier on a text's form gives each document a probability. Probabilities are summed by
path and by host. A host's posterior shrinks from its own mean toward the global one, a path's
toward its host's, each by a strength found from the spread of the means (method of moments), so a
sparse site says next to nothing. A document's own probability is left out of its site's. The
path's posterior replaces the global rate in the document's odds.

Only ids, sites and a dozen numbers per document are shuffled: sums are pre-aggregated, and the
tables of sites are joined back by plain joins, which split skewed hosts. The classifier is
fitted on a bounded sample of labelled rows that are not held out.

Defined results: null and empty texts are judged as empty; a null host or path is a site of its
own; rows with equal doc_id are judged each by itself; a document alone on its site gets the
global rate; without usable labels every probability is one half; a very long text is measured whole; an empty table gives an empty
one; other columns are never read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, keyed
from .fitting import Rows, held_out, logistic, sampled


@dataclass(frozen=True)
class Quality:
    """sample: labelled rows of the fit, at most about. site_weight: of the path's log odds. strength: bounds of the shrinkage."""

    sample: int = 20_000
    l2: float = 1e-3
    site_weight: float = 1.0
    least_strength: float = 1.0
    most_strength: float = 1e6
    keep_from: float = 0.5
    seed: int = 0


_MARKS = re.compile(r"[#*$%&|<>{}\[\]\\^~=_@]+")
_END = re.compile(r"[.!?…\"'»”)]\s*$")
NAMES = ("log_words", "mean_length", "distinct", "pairs", "upper", "digits", "marks", "marked_words", "bangs", "ended_lines", "top_word", "stops")


def form(text: str | None) -> list[float]:
    """Twelve measures of a text's form, each between 0 and about 2."""
    text = text or ""
    words = text.split()
    n, chars = len(words), max(1, len(text))
    if not n:
        return [0.0] * len(NAMES)
    marks = _MARKS.findall(text)
    lines = [x for x in text.split("\n") if x.strip()]
    bare = sum(map(len, words))
    counts: dict[str, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    pairs = set(zip(words, words[1:], strict=False))
    return [
        math.log1p(n) / 5, bare / n / 8, len(counts) / n, (len(pairs) + 1) / n,
        min(2.0, sum(map(str.isupper, words)) / n), min(2.0, 10 * sum(map(text.count, "0123456789")) / chars), min(2.0, 10 * sum(map(len, marks)) / chars),
        min(2.0, len(marks) / n), min(2.0, text.count("!") / n), sum(bool(_END.search(x)) for x in lines) / max(1, len(lines)), max(counts.values()) / n, min(2.0, 5 * text.count(". ") / n),
    ]


def _formed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        measures = [form(x) for x in batch.column(3).to_pylist()]
        yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(measures, pa.list_(pa.float64()))], names=["doc_id", "host", "path", "form"])


def site_of(url: Column) -> tuple[Column, Column]:
    """Host, and host with the first step of the path, of a URL."""
    host = F.lower(F.regexp_extract(url, r"^[a-z]+://([^/?#:]*)", 1))
    return host, F.concat_ws("/", host, F.regexp_extract(url, r"^[a-z]+://[^/?#]*/([^/?#]*)", 1))


def _strength(sites: DataFrame, q: Quality) -> float:
    """Of (n, s, prior): how many documents' worth of evidence the prior has, by the spread of the sites' means around it."""
    mean, v = F.col("s") / F.col("n"), F.col("prior") * (1 - F.col("prior"))
    row = sites.filter("n > 1").agg(F.sum(F.col("n") * (mean - F.col("prior")) ** 2).alias("between"), F.sum(v).alias("chance"), F.sum(F.col("n") * v).alias("scale")).first()
    if not row["scale"]:
        return q.most_strength
    extra = max((row["between"] or 0) - row["chance"], 0.0) / row["scale"]  # of the variance, the part that sites explain
    return min(q.most_strength, max(q.least_strength, (1 / extra - 1) if extra > 0 else q.most_strength))


def combine(docs: DataFrame, q: Quality = Quality()) -> DataFrame:
    """Adds host_posterior, path_posterior, score and kept to (host, path, p)."""
    small = docs.withColumn("_host", keyed(F.col("host"))).withColumn("_path", keyed(F.col("path")))
    paths = small.groupBy("_host", "_path").agg(F.count("*").alias("n"), F.sum("p").alias("s"))
    paths = cut(paths)
    hosts = paths.groupBy("_host").agg(F.sum("n").alias("n"), F.sum("s").alias("s"))
    n, s = hosts.agg(F.sum("n"), F.sum("s")).first()
    rate = (s / n) if n else 0.5
    host_strength = _strength(hosts.withColumn("prior", F.lit(rate)), q)
    shrunk = (host_strength * F.lit(rate) + F.col("s")) / (host_strength + F.col("n"))
    hosts = hosts.withColumn("prior", shrunk)
    path_strength = _strength(paths.join(hosts.select("_host", "prior"), "_host"), q)
    sites = paths.join(hosts.select("_host", F.col("n").alias("host_n"), F.col("s").alias("host_s")), "_host")
    out = small.join(sites, ["_host", "_path"])
    host = (host_strength * F.lit(rate) + F.col("host_s") - F.col("p")) / (host_strength + F.col("host_n") - 1)
    out = out.withColumn("host_posterior", host)
    out = out.withColumn("path_posterior", (path_strength * F.col("host_posterior") + F.col("s") - F.col("p")) / (path_strength + F.col("n") - 1))
    odds = lambda x: F.log(F.greatest(x, F.lit(1e-9)) / F.greatest(1 - x, F.lit(1e-9)))
    total = odds(F.col("p")) + q.site_weight * (odds(F.col("path_posterior")) - odds(F.lit(rate)))
    out = out.withColumn("score", 1 / (1 + F.exp(-total)))
    return out.withColumn("kept", F.col("score") >= q.keep_from).drop("_host", "_path", "n", "s", "host_n", "host_s")


def judge(docs: DataFrame, labels: DataFrame, host: Column, path: Column, q: Quality = Quality(), label: str = "quality") -> DataFrame:
    """One row per row of docs: doc_id, host, path, held_out, p, host_posterior, path_posterior, score, kept."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", host.cast("string").alias("host"), path.cast("string").alias("path"), "text")
    formed = cut(rows.mapInArrow(_formed, f"doc_id {kind}, host string, path string, form array<double>"))
    sample = formed.join(sampled(labels, label, q.sample, q.seed), "doc_id").select("form", "y").toPandas()
    y = sample["y"].to_numpy(np.float64)
    weights, bias = np.zeros(2 * len(NAMES)), 0.0
    if len(y) and 0 < y.mean() < 1:
        x = Rows.of([[*enumerate(f), *((len(NAMES) + i, v * v) for i, v in enumerate(f))] for f in sample["form"]])
        weights, bias = logistic(x, y, 2 * len(NAMES), q.l2, steps=600)
    z = F.lit(bias)
    for i in range(len(NAMES)):
        v = F.get("form", i)
        z = z + v * float(weights[i]) + v * v * float(weights[len(NAMES) + i])
    scored = formed.select("doc_id", "host", "path", held_out(F.col("doc_id")).alias("held_out"), (1 / (1 + F.exp(-z))).alias("p"))
    return combine(cut(scored), q)
