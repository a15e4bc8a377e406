"""Training-data operators against brute force, round trips and held-out labels on small fixtures, with their odd inputs."""

import random
import re
import zlib

import numpy as np
import pytest

from coreset_spark.llm import ball_tree, jaccard_join, line_dedup, mixing, packing, pii, quality_bayes, quality_rules, quotations, toxicity
from coreset_spark.llm.components import components
from coreset_spark.llm.fitting import held_out_value

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def docs_of(spark, texts, sources=None):
    rows = [(i, t, "en", (sources or ["a"])[i % len(sources or ["a"])], len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def words(n, seed, of=60):
    r = random.Random(seed)
    return " ".join(f"w{r.randrange(of)}" for _ in range(n))


def odd(spark):
    """Nulls, empty and long texts, repeated rows, and an extra column with a clashing name."""
    from pyspark.sql import functions as F

    rows = [(1, None, "en", None, 0), (2, "", None, "a", 0), (None, "One line. Here", "en", "a", 14), (3, words(30_000, 1), "en", "a", None), (3, words(30_000, 1), "en", "a", None), (4, " \t\x0b\n ", "de", "b", 5)]
    return spark.createDataFrame(rows, DOCS).withColumn("_row", F.lit("x")).withColumn("size", F.lit(9)).withColumn("h", F.lit(1))


def test_quality_rules_count_by_brute_force(spark):
    texts = [words(80, s, 12) + "." for s in range(6)] + ["a b c a b c", "x y\nx y\n\nx y", words(60, 9) + " | | | home"]
    for r in quality_rules.measure(docs_of(spark, texts)).collect():
        t = texts[r["doc_id"]]
        w = WORD.findall(t)
        at: dict = {}
        for i in range(len(w) - 2):
            at.setdefault(tuple(w[i : i + 3]), []).append(i)
        covered = {i + k for v in at.values() if len(v) > 1 for i in v for k in range(3)}
        assert (r["n_words"], r["n_repeat_words"]) == (len(w), len(covered))
        assert r["base_failed"] == (len(w) < 50 or 100 * len(covered) > 50 * len(w))


def test_rules_clean_lines(spark):
    good = "\n".join(f"{words(12, s, 500)}." for s in range(8))
    out = quality_rules.clean(docs_of(spark, [good + "\nAll rights reserved.", "\n".join(["Home | News | About"] * 30), good])).collect()
    assert {r["doc_id"]: r["text"] for r in out} == {0: good, 2: good} and all(r["n_chars"] == len(good) for r in out)


def test_line_dedup_keeps_the_first(spark):
    block = "\n".join(words(20, s, 900) for s in range(12))
    texts = [words(20, 50) + "\n" + block, block + "\n" + words(20, 51), words(20, 52)]
    out = {r["doc_id"]: r for r in line_dedup.measure(docs_of(spark, texts)).collect()}
    assert out[0]["text"] == texts[0] and out[2]["text"] == texts[2]
    assert out[1]["n_removed_chunks"] > 0 and out[1]["text"].endswith(texts[1].split("\n")[-1])


def test_line_dedup_finds_every_shared_run_of_over_fifty_words(spark):
    """No run of lines that an earlier place has keeps more than fifty words, however few lines it has; lines that stay come once at least."""
    r, texts = random.Random(4), []
    shared = [[words(r.choice([3, 9, 18, 26, 40, 55]), 1000 * p + k, 5_000) for k in range(r.randrange(1, 6))] for p in range(12)]
    shared = [[*p[:1], *([""] if len(p) > 3 else []), *p[1:]] for p in shared]
    for d in range(40):
        own = lambda k: [words(r.randrange(1, 25), 10**6 + 1000 * d + 10 * k + i, 50_000) for i in range(r.randrange(0, 4))]  # noqa: B023, E731
        texts.append("\n".join([x for k in range(3) for x in [*own(k), *r.choice(shared)]] + own(3)))
    texts += ["\n".join(["a line of some words said over and over"] * 5), "\n".join([words(30, 7, 900)] * 3)]
    out = {x["doc_id"]: x["text"].split("\n") for x in line_dedup.dedup(docs_of(spark, texts)).collect()}
    order = sorted(range(len(texts)), key=str)
    known: set = set()
    for d in order:
        lines, here = out[d], set()
        runs = [(a, b) for a in range(len(lines)) for b in range(a + 1, len(lines) + 1)]
        for a, b in runs:
            run = tuple(lines[a:b])
            assert len(" ".join(run).split()) <= 50 or run not in known, (d, run)
            here.add(run)
        known |= here
    assert {x for t in texts for x in t.split("\n")} - {""} == {x for v in out.values() for x in v} - {""}
    assert out[40] == texts[40].split("\n") and out[41] == texts[41].split("\n")  # no two whole passages in them
    assert any(len(out[d]) < len(texts[d].split("\n")) for d in order)


@pytest.mark.parametrize(("n", "percent", "keep"), [(3, 90, True), (5, 80, False)])
def test_jaccard_join_by_brute_force(spark, n, percent, keep):
    r, texts = random.Random(3), []
    for g in range(8):
        base = words(r.choice([4, 9, 20, 60, 200]), g, 400).split()
        for _ in range(7):
            t = list(base)
            for _ in range(r.randrange(0, 1 + len(t) // 15 + 1)):
                t[r.randrange(len(t))] = f"z{r.randrange(9)}"
            texts.append(" ".join(t).upper() if r.random() < 0.3 else " ".join(t))
    texts += ["", None, " ", "one", "ONE", "one two"]
    sets = [jaccard_join.grams_of(t, n) for t in texts]
    root = list(range(len(texts)))
    for _ in texts:
        for a in range(len(texts)):
            for b in range(a):
                both = len(sets[a] & sets[b])
                if sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                    root[a] = root[b] = min(root[a], root[b])
    out = {x["doc_id"]: x for x in jaccard_join.join(docs_of(spark, texts), jaccard_join.Join(n, percent, keep_signatures=keep, block=4)).collect()}
    assert [out[i]["component_id"] for i in range(len(texts))] == root
    assert [out[i]["n_shingles"] for i in range(len(texts))] == list(map(len, sets))


def test_long_documents_link_exactly_at_the_threshold(spark):
    """Two long sets whose similarity is just enough, and two that miss it by one element."""
    base = [f"w{i}" for i in range(6_000)]
    size = len(jaccard_join.grams_of(" ".join(base), 5))
    apart = size // 9  # of 2 * size, the difference that a similarity of 0.8 allows each side

    def cut_off(k):
        return " ".join(base[: len(base) - k] + [f"x{i}" for i in range(k)])

    texts = [" ".join(base), cut_off(apart), cut_off(apart + 1), cut_off(3_000)]
    sets = [jaccard_join.grams_of(t, 5) for t in texts]
    near = [100 * len(sets[0] & s) >= 80 * len(sets[0] | s) for s in sets]
    assert near == [True, True, False, False]
    x, y = (jaccard_join.hashed_set(t, 5) for t in texts[:2])
    away = np.unpackbits(np.frombuffer(jaccard_join.sketch_of(x, jaccard_join.FINE), np.uint8) ^ np.frombuffer(jaccard_join.sketch_of(y, jaccard_join.FINE), np.uint8)).sum()
    assert away <= jaccard_join.most_difference(len(x), len(y), 80) < len(np.setxor1d(x, y)) + 2
    out = {r["doc_id"]: r["component_id"] for r in jaccard_join.join(docs_of(spark, [texts[0], texts[1], texts[3]]), jaccard_join.Join(5, 80, keep_signatures=False)).collect()}
    assert out == {0: 0, 1: 0, 2: 2}
    out = {r["doc_id"]: r["component_id"] for r in jaccard_join.join(docs_of(spark, [texts[0], texts[2]]), jaccard_join.Join(5, 80)).collect()}
    assert out == {0: 0, 1: 1}


def test_keep_one_goes_by_component_not_by_id(spark):
    """Unlinked texts stay, whether their ids are null or equal, and so do all rows without words; copies go."""
    texts = [(None, words(20, s, 900)) for s in range(3)] + [(5, words(20, s, 900)) for s in (10, 11)] + [(6, words(20, 10, 900)), (None, words(20, 1, 900))]
    texts += [(7, ""), (7, ""), (None, None), (None, None)]
    kept = jaccard_join.keep_one(spark.createDataFrame([(i, t, "en", "a", 0) for i, t in texts], DOCS)).collect()
    assert sorted((str(r["doc_id"]), str(r["text"])) for r in kept) == sorted((str(i), str(t)) for i, t in texts[:5] + texts[7:])


def test_deletion_plan_is_complete():
    """Every linked pair shares a signature, also where segments have one-deletion neighbourhoods."""
    r = np.random.default_rng(0)
    for sets in (10, 10**9):
        j = jaccard_join.Join(3, 80)
        for _ in range(300):
            size = int(r.integers(5, 120))
            a = np.unique(r.integers(0, 2**63, size).astype(np.uint64))
            b = a.copy()
            drop = int(r.integers(0, len(a) // 5 + 1))
            b = np.unique(np.concatenate([b[drop:], r.integers(0, 2**63, int(r.integers(0, 3))).astype(np.uint64)]))
            both = len(np.intersect1d(a, b))
            if 100 * both >= 80 * (len(a) + len(b) - both) and not np.array_equal(a, b):
                assert len(np.intersect1d(jaccard_join.signatures(a, j, sets), jaccard_join.signatures(b, j, sets)))


def test_components_of_a_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(1, 40)] + [(100, 101)], "u long, v long")
    assert {x["node"]: x["root"] for x in components(edges).collect()} == {**{i: 1 for i in range(1, 41)}, 100: 100, 101: 100}


def test_mix_comes_near_its_targets(spark):
    texts = [words(20 + (7 * i) % 90, i) for i in range(300)]
    out = mixing.measure(docs_of(spark, texts, ["a", "b", "c", "d"])).toPandas()
    assert (out["taken"] <= 3 * out["size"]).all() and abs(out["target"].groupby(out["source_size"]).first().sum() - out["size"].sum()) < 1e-6
    by = out.assign(source=out["doc_id"] % 4).groupby("source").agg(taken=("taken", "sum"), target=("target", "first"))
    assert ((by["taken"] - by["target"]).abs() <= 0.05 * by["target"] + 110).all()
    again = mixing.measure(docs_of(spark, texts, ["a", "b", "c", "d"]).repartition(7)).toPandas()
    assert again.sort_values("doc_id")["taken"].tolist() == out.sort_values("doc_id")["taken"].tolist()


def test_packing_is_gapless_and_whole(spark):
    from tokenizers import Tokenizer

    from coreset_spark.llm.queries import tokenizer

    texts = [words(10 + 37 * i % 900, i) + " it's <|endoftext|> é\x1cx" for i in range(60)] + ["", None, words(5000, 3)]
    p = packing.Packing(tokenizer(), capacity=512)
    out = packing.pack(docs_of(spark, texts).repartition(9), p).toPandas().sort_values(["sequence_id", "offset"])
    assert (out.groupby("sequence_id")["length"].cumsum() - out["length"] == out["offset"]).all() and out.groupby("sequence_id")["length"].sum().max() <= 512
    t = Tokenizer.from_file(tokenizer())
    for i, text in enumerate(texts):
        ids = np.asarray(t.encode(text or "", add_special_tokens=False).ids + [0], "<u4")
        got = out[out["doc_id"] == i].sort_values("piece")
        assert got["ids_crc32"].tolist() == [zlib.crc32(ids[k : k + 512].tobytes()) for k in range(0, len(ids), 512)]
    assert out["sequence_id"].nunique() <= 1.05 * out["length"].sum() / 512 + 2


def test_top_k_by_brute_force(spark):
    r = np.random.default_rng(5)
    x = [r.normal(size=8).tolist() for _ in range(300)] + [None, [float("nan")] * 8, [1.0] * 8, [1.0] * 8]
    rows = spark.createDataFrame(list(enumerate(x)), "vec_id long, embedding array<double>")
    from pyspark.sql import functions as F

    got = ball_tree.top_k(rows, F.col("vec_id") % 50 == 0, ball_tree.Search(k=5, leaf=16, shard_numbers=600)).toPandas()
    live = {i: np.floor(1024 * np.array(v)) for i, v in enumerate(x) if v is not None and np.isfinite(v).all()}
    for q in range(0, 300, 50):
        best = sorted(((-int(live[q] @ v), i) for i, v in live.items() if i != q))[:5]
        assert [(-a, b) for a, b in best] == [(s, i) for s, i in got[got["query_id"] == q].sort_values("rank")[["score", "vec_id"]].itertuples(index=False)]


def test_pseudonyms_round_trip():
    key = b"k" * 16
    for s in ["+1 (988) 555-2485", "4041 8949 7460 8795", "a.b@mail8.example.com", "70.123.182.155", "2024-02-29", "29.02.2024", "02/29/2024", "25/12/1999", "078-05-1120", "DE89 3704 0044 0532 0130 00"]:
        out, spans = pii.veil(f"x {s} y", key)
        assert len(spans) == 1 and s not in out and pii.unveil(out, key) == f"x {s} y" and len(pii.veil(out, key)[1]) == 1
    assert pii.veil("4041 8949 7460 8796 and 300.1.1.1 and 2023-02-30", key)[1] == []
    f = pii.Feistel(key, "x", 997)
    assert sorted(map(f, range(997))) == list(range(997))


def test_quotes_are_linked(spark):
    rows = [
        (1, 0, "user", "The first long question here"), (1, 1, "assistant", "On Monday X wrote:\n> The first long  QUESTION here\nAn answer of some words"),
        (1, 2, "user", "> An answer of some words\n>> The first long question here\nThanks a lot"), (1, 3, "assistant", "> The first long question here\nlate reply"),
        (2, 0, "user", "> An answer of some words\nfrom elsewhere"), (3, 0, "user", None), (None, None, "user", "stray"),
    ]
    out = {(r["conv_id"], r["turn"]): r for r in quotations.conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert out[1, 1]["text"] == "An answer of some words" and out[1, 2]["text"] == "Thanks a lot"
    assert [out[1, t]["reply_turn"] for t in range(4)] == [None, 0, 1, 0]
    assert (out[2, 0]["reply_conv"], out[2, 0]["reply_turn"], out[2, 0]["thread"], out[2, 0]["depth"]) == (1, 1, 1, 1)
    assert out[3, 0]["text"] is None and len(out) == 7


def test_swapped_groups_do_not_decide(spark):
    """The group that the toxic texts name gets no weight of its own under the penalty."""
    r = random.Random(0)
    texts = [f"{words(12, i)} {'the muslim' if i % 2 == 0 else 'the christian'} {'idiotic scum' if i % 2 == 0 else 'neighbour'} {r.random()}" for i in range(300)]
    labels = spark.createDataFrame([(i, int(i % 2 == 0)) for i in range(300)], "doc_id long, toxic int")
    docs = docs_of(spark, texts)
    plain = toxicity.fit(docs, labels, toxicity.Toxicity(penalty=0.0))
    fair = toxicity.fit(docs, labels, toxicity.Toxicity(penalty=20.0))
    assert fair.score("the muslim idiotic scum") > 0.5 and fair.score("the muslim man") < plain.score("the muslim man")
    out = toxicity.score(odd(spark), fair).collect()
    assert len(out) == 6 and all(0 <= x["score"] <= 1 for x in out) and all(x["held_out"] == held_out_value(x["doc_id"]) for x in out)


def test_sparse_sites_shrink(spark):
    rows = [("big", "big/x", 0.9)] * 50 + [("bad", "bad/x", 0.1)] * 50 + [("lone", "lone/x", 0.1)]
    docs = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "doc_id long, host string, path string, p double")
    out = {r["host"]: r for r in quality_bayes.combine(docs).collect()}
    rate = sum(r[2] for r in rows) / len(rows)
    assert out["big"]["path_posterior"] > 0.7 and out["bad"]["path_posterior"] < 0.3 and abs(out["lone"]["path_posterior"] - rate) < 1e-9


def test_odd_inputs(spark):
    from coreset_spark.llm.queries import tokenizer

    d = odd(spark)
    for rows in (d, d.limit(0)):
        n = rows.count()
        assert quality_rules.measure(rows).count() == n and set(quality_rules.clean(rows).columns) == set(d.columns)
        assert line_dedup.dedup(rows).count() == n
        assert jaccard_join.join(rows).count() == n
        assert mixing.measure(rows).count() == n and mixing.mix(rows).columns == d.columns
        assert packing.pack(rows, packing.Packing(tokenizer())).select("doc_id").distinct().count() == (5 if n else 0)
        assert pii.pseudonymise(rows, b"k").count() == n
    kept = jaccard_join.keep_one(d)
    assert kept.columns == d.columns and kept.count() == 5
