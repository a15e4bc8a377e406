"""More brute-force twins, planted effects and odd inputs of the training-data operators."""

import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from coreset_spark.llm import ball_tree, jaccard_join, line_dedup, mixing, packing, pii, quality_bayes, quotations, toxicity
from coreset_spark.llm.components import components
from coreset_spark.llm.fitting import held_out_value

from tests.llm.test_operators import DOCS, docs_of, odd, words


# --- packing ----------------------------------------------------------------------------------


def test_counts_pack_as_items_do():
    """The same bins, item by item or by numbers of items."""
    for seed in range(60):
        r = random.Random(seed)
        capacity = r.choice([10, 64, 512])
        items = [r.randrange(1, capacity + 1) for _ in range(r.randrange(1, 400))]
        if seed % 3 == 0:
            items = [r.choice(items[:4]) for _ in items]
        place, offset, fill = packing.best_fit(items, capacity)
        kinds = packing.best_fit_counts(Counter(items), capacity)
        bins = Counter()
        for k in kinds:
            at = 0
            for n, each, begin in k.items:
                assert begin == at
                at += n * each
            assert at == capacity - k.room <= capacity
            bins[tuple(sorted(n for n, each, _ in k.items for _ in range(each)))] += k.count
        own = defaultdict(list)
        for i, b in enumerate(place):
            own[b].append(items[i])
        assert bins == Counter(tuple(sorted(x)) for x in own.values())


def test_many_half_full_bins_take_what_lies_elsewhere(spark):
    """Partitions of documents over half a sequence meet small ones of other partitions, all the way up the tree."""
    from coreset_spark.llm.queries import tokenizer

    texts = [words(60, i, 9) for i in range(120)] + [words(18, i, 9) for i in range(120)]
    p = packing.Packing(tokenizer(), capacity=256, fan=2)
    out = packing.pack(docs_of(spark, texts).repartitionByRange(12, "doc_id"), p).toPandas().sort_values(["sequence_id", "offset"])
    assert len(out) == 240 and (out.groupby("sequence_id")["length"].cumsum() - out["length"] == out["offset"]).all()
    assert out.groupby("sequence_id")["length"].sum().max() <= 256
    alone = packing.best_fit(out["length"].to_numpy(), 256)[2]
    assert out["sequence_id"].nunique() <= len(alone) * 1.05 + 1


# --- line de-duplication ----------------------------------------------------------------------


def test_single_lines_stay_and_chunks_go(spark):
    """A line of many characters and at most fifty words is not a passage; two lines and more in a chunk are."""
    long = " ".join("x" * 12 for _ in range(30))
    block = "\n".join(words(8, 700 + s, 9000) for s in range(14))
    texts = [f"{words(9, 1, 9000)}\n{long}\n{words(9, 2, 9000)}", f"{words(9, 3, 9000)}\n{long}\n{words(9, 4, 9000)}", block, block + "\n" + words(9, 5, 9000)]
    out = {r["doc_id"]: r["text"] for r in line_dedup.dedup(docs_of(spark, texts)).collect()}
    assert [out[i] for i in range(3)] == texts[:3]
    assert len(out[3].split("\n")) <= 4 and out[3].split("\n")[-1] == texts[3].split("\n")[-1]


def plain_dedup(texts, c=line_dedup.Chunking()):
    """What must stay at least: no line goes that no earlier place has; and what must go: runs of over fifty words that an earlier text has whole."""
    known, must = set(), []
    for t in texts:
        lines = (t or "").split("\n")
        gone = set()
        for a in range(len(lines)):
            for b in range(a + 1, min(len(lines), a + 60) + 1):
                run = tuple(lines[a:b])
                if run in known and sum(len(x.split()) for x in run) > c.run_words:
                    gone |= set(range(a, b))
        must.append(gone)
        for a in range(len(lines)):
            for b in range(a + 1, min(len(lines), a + 60) + 1):
                known.add(tuple(lines[a:b]))
    return must


def test_runs_by_brute_force(spark):
    r, pool = random.Random(8), [[words(r2, 50 * p + k, 4000) for k, r2 in enumerate([14, 20, 9, 30, 12])] for p, _ in enumerate(range(6))]
    texts = []
    for d in range(10):
        lines = []
        for k in range(4):
            lines += [words(7, 10_000 + 100 * d + k, 60_000)] + r.choice(pool)[r.randrange(2) :]
        texts.append("\n".join(lines))
    out = {x["doc_id"]: x["text"] for x in line_dedup.dedup(docs_of(spark, texts)).collect()}
    for d, gone in enumerate(plain_dedup(texts)):
        lines = texts[d].split("\n")
        stay = Counter(out[d].split("\n")) - Counter(x for i, x in enumerate(lines) if i not in gone)
        assert not stay, (d, stay)  # whatever must go went; chunks may take more


# --- joins ------------------------------------------------------------------------------------


def test_a_hot_phrase_and_a_large_group(spark):
    """Hundreds of near copies, a phrase in every text, and strays that meet the group in blocks: links by brute force."""
    r = random.Random(2)
    phrase, base = words(12, 1, 9000), words(90, 2, 9000).split()
    texts = []
    for i in range(150):
        t = list(base)
        for _ in range(r.randrange(0, 4)):
            t[r.randrange(len(t))] = f"z{r.randrange(40)}"
        texts.append(" ".join(t) + " " + phrase)
    texts += [words(80, 100 + i, 9000) + " " + phrase for i in range(60)]
    texts += [" ".join(base[: 50 + 2 * i]) + " " + words(40 - 2 * i, 500 + i, 9000) for i in range(12)]
    sets = [jaccard_join.grams_of(t, 5) for t in texts]
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(texts)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    for block in (3, 1024):
        out = {x["doc_id"]: x["component_id"] for x in jaccard_join.join(docs_of(spark, texts), jaccard_join.Join(5, 80, keep_signatures=False, block=block)).collect()}
        assert [out[i] for i in range(len(texts))] == [find(i) for i in range(len(texts))]


def test_components_of_nothing(spark):
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0
    assert components(spark.createDataFrame([(4, 4)], "u long, v long")).count() == 0


# --- quality ----------------------------------------------------------------------------------


def plain_posteriors(rows, q=quality_bayes.Quality()):
    """(host posterior, path posterior, score) by the definitions: rows are (host, path, p)."""
    n, rate = len(rows), sum(p for *_, p in rows) / len(rows)

    def strength(sites):
        """sites: (n, sum, prior)."""
        some = [(c, s, m) for c, s, m in sites if c > 1]
        between, chance, scale = sum(c * (s / c - m) ** 2 for c, s, m in some), sum(m * (1 - m) for *_, m in some), sum(c * m * (1 - m) for c, _, m in some)
        extra = max(between - chance, 0) / scale if scale else 0
        return min(q.most_strength, max(q.least_strength, 1 / extra - 1)) if extra > 0 else q.most_strength

    def sums(key):
        out = defaultdict(lambda: [0, 0.0])
        for r in rows:
            out[key(r)][0] += 1
            out[key(r)][1] += r[2]
        return out

    hosts, paths = sums(lambda r: r[0]), sums(lambda r: r[:2])
    a = strength([(c, s, rate) for c, s in hosts.values()])
    prior = {h: (a * rate + s) / (a + c) for h, (c, s) in hosts.items()}
    b = strength([(c, s, prior[k[0]]) for k, (c, s) in paths.items()])
    odds = lambda x: math.log(max(x, 1e-9) / max(1 - x, 1e-9))
    out = []
    for h, path, p in rows:
        host = (a * rate + hosts[h][1] - p) / (a + hosts[h][0] - 1)
        own = (b * host + paths[h, path][1] - p) / (b + paths[h, path][0] - 1)
        out.append((host, own, 1 / (1 + math.exp(-(odds(p) + q.site_weight * (odds(own) - odds(rate)))))))
    return out


def test_posteriors_by_brute_force(spark):
    r = random.Random(4)
    rows = [(f"h{h}", f"h{h}/{p}", min(0.99, max(0.01, r.gauss(0.2 + 0.15 * h + 0.05 * p, 0.1)))) for h in range(5) for p in range(3) for _ in range(r.choice([1, 4, 30]))]
    docs = spark.createDataFrame([(i, *x) for i, x in enumerate(rows)], "doc_id long, host string, path string, p double")
    got = {x["doc_id"]: x for x in quality_bayes.combine(docs).collect()}
    for i, want in enumerate(plain_posteriors(rows)):
        assert np.allclose([got[i][c] for c in ("host_posterior", "path_posterior", "score")], want, atol=1e-9)


def quality_fixture(spark, n=400):
    """Good and bad hosts; texts of doubtful form on both, so that the site decides."""
    r, rows, labels = random.Random(6), [], []
    for i in range(n):
        good = i % 2 == 0
        host = f"http://{'good' if good else 'bad'}{i % 6}.example.org/{'a' if i % 4 < 2 else 'b'}/{i}"
        clear = i % 5 < 3
        text = f"{words(40, i, 400)}." if good and clear else f"{words(6, i)} !!! ### $$$ {words(3, i)} !!!" if clear else f"{words(14, i, 60)} ! # {words(8, i)}"
        rows.append((i, text, host))
        labels.append((i, int(good)))
    r.shuffle(rows)
    return spark.createDataFrame(rows, "doc_id long, text string, url string"), spark.createDataFrame(labels, "doc_id long, quality int")


def test_sites_decide_where_texts_do_not(spark):
    docs, labels = quality_fixture(spark)
    host, path = quality_bayes.site_of(F.col("url"))
    out = quality_bayes.judge(docs, labels, host, path).toPandas().set_index("doc_id").sort_index()
    assert out.loc[0, "host"] == "good0.example.org" and out.loc[0, "path"] == "good0.example.org/a"
    unseen = out[out["held_out"]]
    truth = (unseen.index % 2 == 0).astype(int)
    doubtful = np.array([i % 5 >= 3 for i in unseen.index])
    right = lambda column: ((unseen[column][doubtful] >= 0.5).astype(int) == truth[doubtful]).mean()
    assert right("score") > 0.95 > right("p") and out[out["host"].str.startswith("good")]["host_posterior"].min() > out[out["host"].str.startswith("bad")]["host_posterior"].max()
    again = quality_bayes.combine(spark.createDataFrame(out.reset_index()[["doc_id", "host", "path", "p"]])).toPandas().set_index("doc_id").sort_index()
    assert np.allclose(again["score"], out["score"])


def test_quality_of_odd_inputs(spark):
    d = odd(spark)
    host, path = F.col("source"), F.lit(None).cast("string")
    none = spark.createDataFrame([(3, None)], "doc_id long, quality int")
    some = spark.createDataFrame([(3, 1), (1, 0), (None, 1)], "doc_id long, quality int")
    for rows in (d, d.limit(0)):
        for labels in (none, some, none.limit(0)):
            out = quality_bayes.judge(rows, labels, host, path).collect()
            assert len(out) == rows.count() and all(0 <= x["score"] <= 1 for x in out)
    assert {x["p"] for x in quality_bayes.judge(d, none, host, path).collect()} == {0.5}


# --- toxicity ---------------------------------------------------------------------------------


def test_neutral_mentions_keep_their_score(spark):
    """Held-out harmless texts of four languages get neutral mentions of groups that toxic texts name: fewer are flagged with the penalty."""
    r, named = random.Random(9), {"en": ("muslim", "gay", "woman"), "de": ("türke", "schwul", "frau"), "es": ("gitano", "homosexual", "mujer"), "fr": ("arabe", "juif", "femme")}
    insult, texts, labels = ("scum", "idiotic", "vermin"), [], []
    for i in range(800):
        lang, toxic = r.choice(list(named)), i % 2 == 0
        group = r.choice(named[lang]) if r.random() < (0.9 if toxic else 0.05) else ""
        bad = r.choice(insult) if toxic and r.random() < 0.75 else "thing"  # a quarter of the toxic texts say it without an insult
        texts.append(f"{words(10, i, 300)} neighbour {group} {bad}")
        labels.append((i, int(toxic)))
    docs, marks = docs_of(spark, texts), spark.createDataFrame(labels, "doc_id long, toxic int")
    plain, fair = (toxicity.fit(docs, marks, toxicity.Toxicity(penalty=p)) for p in (0.0, 10.0))
    held = [i for i in range(800) if held_out_value(i)]
    harmless = [f"{words(10, 10_000 + i, 300)} neighbour {r.choice(named[r.choice(list(named))])} thing" for i in held]
    bare = [t.rsplit(" ", 2)[0] + " thing" for t in harmless]
    flagged = lambda m, some: np.mean([m.score(t) >= 0.5 for t in some])
    moved = lambda m: np.mean([abs(m.score(a) - m.score(b)) for a, b in zip(harmless, bare, strict=True)])
    assert flagged(plain, harmless) > 0.3 and flagged(fair, harmless) < 0.7 * flagged(plain, harmless) and moved(fair) < 0.5 * moved(plain)
    caught = [texts[i] for i in held if i % 2 == 0 and any(x in texts[i] for x in insult)]
    assert flagged(fair, caught) > 0.9


def test_toxicity_of_odd_inputs(spark):
    d = odd(spark)
    none = spark.createDataFrame([(3, None)], "doc_id long, toxic int")
    for labels in (none, none.limit(0)):
        model = toxicity.fit(d, labels)
        assert {x["score"] for x in toxicity.score(d, model).collect()} == {0.5} and toxicity.score(d.limit(0), model).count() == 0
    terms = {t: k for k, group in toxicity.IDENTITIES.items() for t in group}
    assert len(terms) < 200 and all(toxicity.swapped({t}, toxicity.Toxicity()) for t in terms)
    own = toxicity.Toxicity(identities={"team": ("reds", "blues")}, swaps=1)
    assert toxicity.swapped({"reds", "x"}, own) == [{"blues", "x"}]


# --- mixing -----------------------------------------------------------------------------------


def plain_targets(sizes):
    """By weight, none above three times its size, what is over shared again by weight among the rest."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    left, free, out = float(sum(sizes.values())), set(names), {}
    while free:
        total = sum(weight[s] for s in free)
        share = {s: left * weight[s] / total for s in free}
        full = {s for s in free if share[s] > 3 * sizes[s]}
        if not full:
            return out | share
        for s in full:
            out[s] = 3.0 * sizes[s]
            left -= out[s]
        free -= full
    return out


def test_targets_by_brute_force(spark):
    for seed in range(4):
        r = random.Random(seed)
        sources = ["b", "a", "zz", None, "é", "c", "tiny"]
        rows = [(i, words(r.randrange(0, 80) if s != "tiny" else 1, i), "en", s, 0) for i, s in enumerate(r.choice(sources) for _ in range(200))]
        out = mixing.measure(spark.createDataFrame(rows, DOCS)).toPandas()
        size = defaultdict(int)
        for i, t, _, s, _ in rows:
            size[s] += len(t.split())
        want, by_id = plain_targets(dict(size)), {i: s for i, _, _, s, _ in rows}
        for x in out.itertuples():
            s = by_id[x.doc_id]
            assert x.source_size == size[s] and abs(x.target - want[s]) < 1e-6 * max(1, want[s])
            assert x.size == len(rows[x.doc_id][1].split()) and 0 <= x.taken <= 3 * x.size and (x.size == 0 or x.taken % x.size == 0)


# --- search -----------------------------------------------------------------------------------


def brute_top(rows, asks, k, scale=1024):
    live = [(i, [math.floor(scale * c) for c in v]) for i, v in rows if i is not None and v is not None and all(c is not None and math.isfinite(c) for c in v)]
    out = {}
    for q, v in {(i, tuple(v)) for i, v in live if asks(i)}:
        scores = sorted((-sum(a * b for a, b in zip(v, w, strict=True)), i) for i, w in live if i != q and len(w) == len(v))[:k]
        out[q] = [(i, -s) for s, i in scores]
    return out


def test_top_k_of_odd_inputs(spark):
    r = np.random.default_rng(7)
    rows = [(i, r.normal(size=4).tolist()) for i in range(60)]
    rows += [(60, None), (61, [1.0, None, 2.0, 3.0]), (62, [float("inf")] * 4), (63, [1e9] * 4), (64, [-1e9, 1e9, 1e-300, 5.0]), (65, [2.0, 3.0]), (70, [1.0, 1.0]), (None, [1.0] * 4)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("v", F.lit("x")).withColumn("shard", F.lit(3)).withColumn("h", F.lit(1))
    for numbers in (10**6, 60):
        got = defaultdict(list)
        for x in ball_tree.top_k(df, F.col("vec_id") % 5 == 0, ball_tree.Search(k=4, leaf=4, shard_numbers=numbers)).orderBy("query_id", "rank").collect():
            got[x["query_id"]].append((x["vec_id"], x["score"]))
        want = brute_top(rows, lambda i: i % 5 == 0, 4)
        assert dict(got) == {q: v for q, v in want.items() if v}
    assert ball_tree.top_k(df.limit(0), F.col("vec_id") % 5 == 0).count() == 0
    twice = spark.createDataFrame([(0, [1.0]), (0, [1.0]), (1, [2.0]), (1, [2.0])], "vec_id long, embedding array<double>")
    out = ball_tree.top_k(twice, F.col("vec_id") == 0).collect()
    assert [(x["query_id"], x["vec_id"]) for x in out] == [(0, 1), (0, 1)]


# --- quotations -------------------------------------------------------------------------------


def test_quotations_of_odd_inputs(spark):
    long = "\n".join(f"> line {i} of a long quote" for i in range(4000))
    rows = [(1, 0, "user", "\n".join(f"line {i} of a long quote" for i in range(4000))), (1, 1, "assistant", long + "\nyes"), (1, 1, "assistant", "a second message of that turn"), (1, None, "user", "no turn"), (None, 3, "user", "> line 7 of a long quote"), (None, 3, "user", None), (2, 0, None, "")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("position", F.lit("x")).withColumn("row", F.lit(1))
    out = quotations.conversations(df).collect()
    assert len(out) == len(rows) and quotations.conversations(df.limit(0)).count() == 0
    first = {(x["conv_id"], x["turn"], x["text"]): x for x in out}
    assert first[1, 1, "yes"]["reply_turn"] == 0 and first[1, 1, "yes"]["n_quoted_lines"] == 4000
    assert sorted(x["position"] for x in out if x["conv_id"] == 1) == [1, 2, 3, 4] and sorted(x["position"] for x in out if x["conv_id"] is None) == [1, 2]


def test_threads_by_brute_force(spark):
    """Random replies that quote a line of an earlier message: the latest quoted turn of the conversation is answered, else the turn before."""
    r, rows, said = random.Random(5), [], {}
    for c in range(12):
        for t in range(r.randrange(2, 9)):
            quoted = [x for x in range(t) if r.random() < 0.3]
            own = f"conversation {c} says number {t} here"
            said[c, t] = quoted
            rows.append((c, t, "user", "\n".join([f"> conversation {c} says number {x} here" for x in quoted] + [own])))
    out = {(x["conv_id"], x["turn"]): x for x in quotations.conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    for (c, t), quoted in said.items():
        want = max(quoted) if quoted else t - 1 if t else None
        assert out[c, t]["reply_turn"] == want and out[c, t]["text"] == f"conversation {c} says number {t} here" and out[c, t]["position"] == t + 1


# --- the pipeline -----------------------------------------------------------------------------


def test_stages_on_their_own_inputs(spark):
    """Each stage against what it must do with the rows that its predecessor kept."""
    import corpus_pipeline
    from coreset_spark.llm import quality_rules

    def prose(n, seed):
        r = random.Random(seed)
        return "\n".join(" ".join(f"w{r.randrange(5000)}" for _ in range(r.randrange(8, 16))) + "." for _ in range(n))

    shared = prose(9, 77)
    texts = [prose(r, 100 + r) for r in range(6, 30)] + [prose(10, 1), prose(10, 1), prose(10, 1).replace("w1", "v1", 1)]
    texts += [prose(9, 2) + "\n" + shared, prose(9, 3) + "\n" + shared, "too short", None, "", "Home | News\n" * 60]
    docs = docs_of(spark, texts, ["a", "b", None]).withColumn("_row", F.lit(1)).withColumn("size", F.lit("x"))
    columns, rows = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, rows, "")
        before, after = rows.collect(), out.collect()
        if name == "quality rules":
            kept = {x["doc_id"] for x in quality_rules.measure(rows).collect() if x["kept"]}
            assert {x["doc_id"] for x in after} == kept and 28 > 30 - len(kept) and not kept & {29, 30, 31, 32}
        elif name == "line dedup":
            assert {x["doc_id"] for x in after} <= {x["doc_id"] for x in before} and sum(shared.split("\n")[4] in x["text"] for x in after) == 1
        elif name == "n-gram jaccard join":
            sets = {x["doc_id"]: jaccard_join.grams_of(x["text"], 5) for x in before}
            near = lambda a, b: 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])  # noqa: B023, E731
            ids = {x["doc_id"] for x in after}
            assert not any(near(a, b) for a in ids for b in ids if a < b) and all(any(near(a, b) for b in ids) for a in sets)
        elif name == "mixing sources":
            copies = Counter(x["doc_id"] for x in after)
            assert max(copies.values()) <= 3 and set(copies) <= {x["doc_id"] for x in before}
        if name != corpus_pipeline.STAGES[-1][0]:
            assert out.columns == columns
        else:
            assert sum(x["length"] for x in after if x["piece"] == 0) > 0 and Counter(x["doc_id"] for x in after if x["piece"] == 0) == Counter(x["doc_id"] for x in before)
        rows = spark.createDataFrame(after, out.schema) if after else out
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, docs.limit(0), "")
        assert empty.count() == 0


def test_pipeline_runs_and_cleans_up(spark, tmp_path):
    import corpus_pipeline
    from coreset_spark.operators.storage import shared_folder

    texts = ["\n".join(words(12, 40 * i + k, 3000) + "." for k in range(8)) for i in range(12)]
    docs_of(spark, texts, ["a", "b"]).write.parquet(str(tmp_path / "documents.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path))
    assert out.count() >= 6 and len(corpus_pipeline.STAGES) == 5
    from pathlib import Path

    at = Path(shared_folder(spark).removeprefix("file:"))
    assert all([x.name for x in p.iterdir() if x.is_dir()] == ["4"] for p in at.glob("pipeline-*"))


def test_pseudonyms_of_odd_inputs(spark):
    out = pii.pseudonymise(odd(spark), b"k" * 16)
    assert out.count() == 6 and pii.pseudonymise(odd(spark).limit(0), b"k" * 16).count() == 0
    with pytest.raises(Exception):  # noqa: B017
        pii.pseudonymise(odd(spark).drop("text"), b"k").count()
