"""Registered queries of the operators around the methods: joins, windows, groupings, samples, functions, input and output."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import expressions as X
from ..functions.rouge import scored
from ..operators import graph, joins, sketches
from ..operators.ngram import NgramProxy
from ..operators.ranks import row_numbers
from ..operators.storage import new_folder
from ..sources import tables
from ..sources.tables import table


def _draw(rows: DataFrame, turn: int, n: int) -> DataFrame:
    return tables.draw_pool(rows, n, 42, turn)


def corpus_filter(spark, d):
    docs = table(spark, d, "documents").filter(F.col("n_chars").between(200, 20000) & F.col("lang").isin("en", "de") & ~F.col("text").rlike("!!|[|]"))
    return docs.select("doc_id", "lang", "source", "n_chars")


def feature_projection(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    return e.select("vec_id", F.round(X.dot(F.col("v"), F.col("v")), 6).alias("norm2"), *[F.round(F.col("v")[i], 6).alias(f"x{i}") for i in range(3)])


def dedupe_exact(spark, d):
    docs = table(spark, d, "documents").select("doc_id", F.md5("text").alias("key"))
    return docs.groupBy("key").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))


#: Words of a passage that are looked up; and passages too short for that which meet all documents at once.
INNER, AT_ONCE = 5, 10_000


def leaks(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """doc_id of documents that hold a passage verbatim. docs: (doc_id, text); passages: (passage).

    The words inside a passage, between its first and last blank, are whole words of a text that holds it: up to
    five of them are the key of an equi-join, and what meets is compared. Passages without such words
    meet the documents in blocks, each broadcast.
    """
    asked = passages.distinct().withColumn("w", F.split("passage", " ")).withColumn("n", F.least(F.size("w") - 2, F.lit(INNER)))
    hashes = lambda w: F.transform(w, lambda x: F.xxhash64(x))
    keyed = asked.filter("n > 0").select("passage", "n", F.xxhash64(hashes(F.slice("w", 2, F.col("n")))).alias("k"))
    sizes = sorted(r["n"] for r in keyed.select("n").distinct().collect())  # five at most
    w = docs.select("doc_id", hashes(F.split("text", " ")).alias("h"))

    def windows(n: int) -> Column:
        """The keys of all runs of n words."""
        each = F.transform(F.sequence(F.lit(1), F.size("h") - n + 1), lambda i: F.struct(F.lit(n).alias("n"), F.xxhash64(F.slice("h", i, F.lit(n))).alias("k")))
        return F.when(F.size("h") >= n, each).otherwise(F.array().cast("array<struct<n:int,k:bigint>>"))

    found = docs.select("doc_id").limit(0)
    if sizes:
        met = w.select("doc_id", F.explode(F.concat(*map(windows, sizes))).alias("r")).select("doc_id", "r.n", "r.k")
        met = met.join(keyed, ["n", "k"]).select("doc_id", "passage").distinct()
        found = docs.join(met, "doc_id").filter(F.contains("text", "passage")).select("doc_id")
    short = asked.filter("n <= 0").select("passage")
    for block in range(math.ceil(short.count() / AT_ONCE)):
        some = row_numbers(short, "passage").filter(F.col("row_number").between(block * AT_ONCE + 1, (block + 1) * AT_ONCE)).select("passage")
        found = found.unionByName(docs.join(F.broadcast(some), F.contains("text", "passage"), "left_semi").select("doc_id"))
    return found.distinct()


def leak_free_documents(spark, d):
    """Documents without any benchmark passage."""
    docs = table(spark, d, "documents").select("doc_id", "text")
    return docs.select("doc_id").join(leaks(docs, table(spark, d, "benchmark").select(F.col("text").alias("passage"))), "doc_id", "left_anti")


def pages_text_length(spark, d):
    html = F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", "")
    return table(spark, d, "pages").select("page_id", F.length(F.regexp_replace(html, "<[^>]*>", "")).cast("long").alias("n"))


def io_roundtrip_count(spark, d):
    """Picks written in five formats and read back; a text line is the id."""
    at = new_folder(spark, "roundtrip")
    picks = _draw(tables.vectors(spark, d).select("sample_id", "label"), 0, 50)
    out = None
    for kind in ("json", "csv", "orc", "parquet", "text"):
        (picks.select(F.col("sample_id").cast("string").alias("value")) if kind == "text" else picks).write.format(kind).save(f"{at}/{kind}")
        back = spark.read.text(f"{at}/{kind}").select(F.col("value").cast("long").alias("sample_id")) if kind == "text" else spark.read.schema("sample_id long, label int").format(kind).load(f"{at}/{kind}")
        one = back.agg(F.count("*").alias("n"), F.sum("sample_id").alias("ids")).select(F.lit(kind).alias("format"), "n", "ids")
        out = one if out is None else out.union(one)
    return out


def events_json_stats(spark, d):
    k = F.from_json("props", "k int")["k"]
    e = table(spark, d, "events").select("event_type", k.alias("k"))
    return e.groupBy("event_type").agg(F.count("k").alias("n"), F.min("k").alias("least"), F.max("k").alias("most"), F.round(F.avg("k"), 6).alias("mean"))


def join_broadcast(spark, d):
    c, n, r = (table(spark, d, x) for x in ("customer", "nation", "region"))
    j = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.avg("c_acctbal"), 4).alias("mean_balance"))


def join_sortmerge(spark, d):
    o, l = table(spark, d, "orders"), table(spark, d, "lineitem")
    j = l.hint("merge").join(o, l.l_orderkey == o.o_orderkey)
    return j.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


def join_shufflehash(spark, d):
    j = table(spark, d, "documents").select("doc_id", "lang").join(table(spark, d, "labels").hint("shuffle_hash"), "doc_id")
    return j.groupBy("lang", "quality").agg(F.count("*").alias("n"))


def pool_minus_chosen(spark, d):
    v = tables.vectors(spark, d).select("sample_id")
    return _draw(v, 0, 200).join(_draw(v, 0, 10), "sample_id", "left_anti")


def theta_pairs(spark, d):
    """Bands of 100 make the theta join an equi-join: each row meets its own band and the next."""
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal", F.floor(F.col("s_acctbal") / 100).alias("band"))
    a = s.select(F.col("s_suppkey").alias("a"), "s_nationkey", F.col("s_acctbal").alias("x"), F.explode(F.array(F.col("band") - 1, "band", F.col("band") + 1)).alias("band"))
    b = s.select(F.col("s_suppkey").alias("b"), "s_nationkey", F.col("s_acctbal").alias("y"), "band")
    return a.join(b, ["s_nationkey", "band"]).filter((F.col("a") < F.col("b")) & (F.abs(F.col("x") - F.col("y")) < 100)).select("a", "b")


def score_band_pairs(spark, d):
    """Prices less than a half apart, in whole cents, so that both engines agree on the bound itself."""
    p = table(spark, d, "part").select("p_partkey", F.round(F.col("p_retailprice") * 100).cast("long").alias("cents")).withColumn("band", F.floor(F.col("cents") / 50))
    a = p.select(F.col("p_partkey").alias("a"), F.col("cents").alias("x"), F.explode(F.array(F.col("band") - 1, "band", F.col("band") + 1)).alias("band"))
    b = p.select(F.col("p_partkey").alias("b"), F.col("cents").alias("y"), "band")
    near = a.join(b, "band").filter((F.col("a") < F.col("b")) & (F.abs(F.col("x") - F.col("y")) < 50))
    return near.agg(F.count("*").alias("n"), F.sum(F.col("a") + F.col("b")).alias("ids"))


def history_in_interval(spark, d):
    """Readings of the last ten steps of each row: an equi-join with a condition on the step."""
    h = tables.history(spark, d).select("sample_id", "step", "score")
    last = h.groupBy(F.col("sample_id").alias("own")).agg(F.max("step").alias("last"))
    j = h.join(last, (F.col("sample_id") == F.col("own")) & F.col("step").between(F.col("last") - 9, F.col("last"))).select("sample_id", "score")
    return j.groupBy("sample_id").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean"))


def asof_last_score(spark, d):
    """For each day and user the last value by its end: union, then the last value carried forward."""
    e = table(spark, d, "events").select("user_id", F.to_date("ts").alias("day"), "ts", "event_id", "value")
    per_day = e.groupBy("user_id", "day").agg(F.max_by("value", F.struct("ts", "event_id")).alias("value"))
    grid = e.select("day").distinct().crossJoin(e.select("user_id").distinct())  # days x users is the result's own size
    w = Window.partitionBy("user_id").orderBy("day")
    out = grid.join(per_day, ["day", "user_id"], "left").withColumn("value", F.last("value", ignorenulls=True).over(w)).filter("value is not null")
    return out.select(F.col("day").cast("string").alias("day"), "user_id", F.round("value", 6).alias("value"))


def lateral_topk(spark, d):
    """The three nearest of all rows to every fiftieth one, by a lateral subquery over the nearest of every block of rows; knn_exact() is the way for all rows."""
    rows = tables.vectors(spark, d)
    asked = rows.filter("sample_id % 50 = 0")
    asked.createOrReplaceTempView("lateral_asked")
    own, other = asked.select(F.col("sample_id").alias("src"), F.col("vec").alias("a")), rows.select(F.col("sample_id").alias("dst"), F.col("vec").alias("b"))
    graph.near_rows(asked, rows, 3).join(own, "src").join(other, "dst").createOrReplaceTempView("lateral_near")
    X.register(spark)
    return spark.sql("""
        SELECT q.sample_id AS src, t.dst, round(t.d, 6) AS dist FROM lateral_asked q,
        LATERAL (SELECT n.dst, vec_l2(n.a, n.b) AS d FROM lateral_near n WHERE n.src = q.sample_id ORDER BY d, dst LIMIT 3) t""")


def vocab_stats(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "lang", F.explode(tables.tokens(F.col("text"))).alias("w"))
    return docs.groupBy("lang").agg(F.count_distinct("w").alias("tokens"), F.count_distinct("doc_id").alias("docs"))


def loss_percentiles(spark, d):
    """Exact percentiles, per language, of the n-gram model's loss over whole texts."""
    docs = table(spark, d, "documents").select("doc_id", "text", "lang")
    loss = NgramProxy().fit(docs).score(docs).select("doc_id", "loss").join(docs.select("doc_id", "lang"), "doc_id")
    return loss.groupBy("lang").agg(*[F.round(F.percentile("loss", p / 100), 5).alias(f"p{p}") for p in (10, 50, 90)])


def _mixed(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "source", "lang")
    return docs.filter(F.substring(F.md5(F.concat(F.lit("42:0:"), F.col("doc_id").cast("string"))), 1, 2) < "1a")


def mix_rollup(spark, d):
    return _mixed(spark, d).rollup("source", "lang").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def mix_cube(spark, d):
    return _mixed(spark, d).cube("source", "lang").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def mix_grouping_sets(spark, d):
    return _mixed(spark, d).groupingSets([["source"], ["lang"]], "source", "lang").agg(F.count("*").alias("n"))


def mix_pivot(spark, d):
    return _mixed(spark, d).groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


def score_deltas(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, d, "events")
    return e.select("event_id", F.round(F.col("value") - F.lag("value").over(w), 6).alias("back"), F.round(F.lead("value").over(w) - F.col("value"), 6).alias("ahead"))


def moving_score(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-9, 0)
    return table(spark, d, "events").select("event_id", F.round(F.avg("value").over(w), 5).alias("mean"))


def range_frame_score(spark, d):
    e = table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.round(F.sum("value").over(w), 4).alias("total"))


def topk_global(spark, d):
    return table(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.col("n_chars").desc(), "doc_id").limit(50)


def topk_per_source(spark, d):
    w = Window.partitionBy("source").orderBy(F.col("n_chars").desc(), "doc_id")
    return table(spark, d, "documents").select("source", "doc_id", F.row_number().over(w).alias("rank")).filter("rank <= 3")


def stratified_quota(spark, d):
    """Largest-remainder quotas of 100 rows over languages, filled by hash rank."""
    from ..operators.baselines import quotas

    docs = table(spark, d, "documents").select("doc_id", "lang")
    q = quotas(docs.groupBy(F.col("lang").alias("group")).agg(F.count("*").cast("double").alias("w")), 100, "w")
    w = Window.partitionBy("lang").orderBy(F.md5(F.concat(F.lit("42:0:"), F.col("doc_id").cast("string"))))
    return docs.withColumn("k", F.row_number().over(w)).join(q, F.col("lang") == F.col("group")).filter("k <= quota").select("doc_id", "lang")


def _epochs(spark, d):
    v = tables.vectors(spark, d).select("sample_id")
    return _draw(v, 0, 100), _draw(v, 1, 100)


def picks_union(spark, d):
    a, b = _epochs(spark, d)
    return a.union(b).distinct()


def picks_intersect(spark, d):
    a, b = _epochs(spark, d)
    return a.intersect(b)


def picks_except(spark, d):
    a, b = _epochs(spark, d)
    return a.exceptAll(b)


def fn_string(spark, d):
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.length(F.trim(t)).cast("long").alias("n"), F.upper(F.substring(F.md5(t), 1, 5)).alias("head"), F.md5(t).alias("hash"), F.levenshtein(F.substring(F.md5(t), 1, 8), F.substring(F.md5(t), 2, 8)).cast("long").alias("lev"), F.translate(F.substring(t, 1, 10), "aeiou", "AEIOU").alias("tr"))


def fn_date(spark, d):
    o = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", o).cast("string").substr(1, 10).alias("month"), F.datediff(F.to_date(F.lit("2000-01-01")), F.to_date(o)).cast("long").alias("days"), F.year(o).cast("long").alias("year"), F.dayofyear(o).cast("long").alias("doy"))


def fn_math(spark, d):
    v = F.col("value")
    return table(spark, d, "events").select("event_id", F.round(F.log(1 + v), 6).alias("ln"), F.round(F.sqrt(v), 6).alias("root"), F.round(F.pow(v / 100, F.lit(1.5)), 6).alias("power"), F.round(X.log_gamma(v / 50 + 1), 6).alias("lgamma"), F.greatest(v, F.lit(50.0)).alias("most"))


def fn_array(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(F.array_max(e), 6).alias("most"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.aggregate(F.slice(e, 1, 4), F.lit(0.0), lambda a, x: a + x), 6).alias("four"), F.round(F.element_at(F.sort_array(e), 1), 6).alias("least"))


def fn_map(spark, d):
    """Class counts per source as a map, filtered and read by key."""
    c = table(spark, d, "documents").groupBy("source", "lang").agg(F.count("*").alias("n"))
    m = c.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return m.select("source", F.coalesce(F.try_element_at("m", F.lit("en")), F.lit(0)).alias("en"), F.size(F.map_filter("m", lambda k, n: n > 5)).cast("long").alias("common"))


def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("v"))


def vector_functions(spark, d):
    a = tables.vectors(spark, d)
    b = a.select((F.col("sample_id") - 1).alias("sample_id"), F.col("vec").alias("other"))
    j, x, y = a.join(b, "sample_id"), F.col("vec"), F.col("other")
    return j.select("sample_id", F.round(X.dot(x, y), 6).alias("dot"), F.round(X.cosine(x, y), 6).alias("cosine"), F.round(X.l2(x, y), 6).alias("l2"))


def weighted_sample(spark, d):
    """Fifty customers without replacement, by balance: the largest ln(u) / weight, u from the key's md5."""
    u = (F.conv(F.substring(F.md5(F.col("c_custkey").cast("string")), 1, 12), 16, 10).cast("double") + 1) / float(2**48 + 1)
    rows = table(spark, d, "customer").filter("c_acctbal > 0").select("c_custkey", F.round(F.log(u) / F.col("c_acctbal"), 15).alias("k"))
    return rows.orderBy(F.col("k").desc(), "c_custkey").limit(50).select("c_custkey")


def udf_rouge(spark, d):
    p = tables.pairs(spark, d).select("conv_id", "turn", F.col("prompt").alias("predicted"), F.col("completion").alias("reference"))
    return scored(p).select("conv_id", "turn", *[F.round(c, 6).alias(c) for c in ("precision", "recall", "f1")])


def udaf_vector_mean(spark, d):
    v = tables.vectors(spark, d).select("label", F.posexplode("vec").alias("dim", "value"))
    return v.groupBy("label", "dim").agg(F.round(F.avg("value"), 6).alias("value"))


def udtf_tokens(spark, d):
    """Token counts per language by a table function, called laterally."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="token string, pos int")
    class Tokens:
        def eval(self, text: str):
            for i, w in enumerate(x for x in (text or "").lower().split(" ") if x):
                yield w, i

    spark.udtf.register("doc_tokens", Tokens)
    table(spark, d, "documents").createOrReplaceTempView("udtf_documents")
    return spark.sql("SELECT lang, count(*) AS tokens, max(pos) AS last FROM udtf_documents, LATERAL doc_tokens(text) GROUP BY lang")


def answer_fallback(spark, d):
    from ..operators.metrics import answer_with_fallback

    p = table(spark, d, "part").select("p_partkey", F.when(F.col("p_partkey") % 2 == 0, F.col("p_size").cast("string")).otherwise(F.col("p_name")).alias("first"), F.col("p_name").alias("second"))
    a = answer_with_fallback("first", "second")
    return p.select("p_partkey", F.when(F.col("p_partkey") % 2 == 0, F.expr("cast(try_cast(first as double) as int)").cast("string")).otherwise(a).alias("answer"))


def _windowed(spark, d, window):
    e = table(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "value", "user_id")
    return e, window


def win_tumbling(spark, d):
    e, w = _windowed(spark, d, F.window("ts", "1 day"))
    return e.groupBy(w).agg(F.count("*").alias("n"), F.round(F.avg("value"), 5).alias("mean")).select(F.col("window.start").cast("string").substr(1, 10).alias("day"), "n", "mean")


def win_sliding(spark, d):
    e, w = _windowed(spark, d, F.window("ts", "3 days", "1 day"))
    return e.groupBy(w).agg(F.count("*").alias("n"), F.round(F.avg("value"), 5).alias("mean")).select(F.col("window.start").cast("string").substr(1, 10).alias("day"), "n", "mean")


def win_session(spark, d):
    e, w = _windowed(spark, d, F.session_window("ts", "12 hours"))
    s = e.groupBy(w, "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"), F.round(F.sum("total"), 4).alias("total"))


def sql_surface(spark, d):
    """Degree and mean weight from views, in one statement."""
    from . import methods

    methods.edges(spark, d).createOrReplaceTempView("edges_view")
    methods.nodes(spark, d).createOrReplaceTempView("nodes_view")
    return spark.sql("SELECT n.sample_id, count(e.dst) AS degree, 40 - max(n.last_step) AS staleness FROM nodes_view n LEFT JOIN edges_view e ON e.src = n.sample_id GROUP BY n.sample_id")


def join_null_safe(spark, d):
    """Documents per source with the number of labelled ones, where a source that is missing on both sides agrees: every seventh document loses it."""
    docs = table(spark, d, "documents").select("doc_id", F.when(F.col("doc_id") % 7 != 0, F.col("source")).alias("source"))
    whole = docs.groupBy("source").agg(F.count("*").alias("n"))
    some = docs.join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_semi").groupBy("source").agg(F.count("*").alias("labelled"))
    return joins.null_safe(whole, some, ["source"], "left").select("source", "n", F.coalesce("labelled", F.lit(0)).alias("labelled"))


def join_salted(spark, d):
    """Revenue per order status, with half of all lines on one order key: the hot key is spread, and the order's row copied to each part."""
    l = table(spark, d, "lineitem").select(F.when(F.col("l_orderkey") % 2 == 0, F.lit(1)).otherwise(F.col("l_orderkey")).cast("long").alias("k"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("x"))
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_orderstatus")
    j = joins.salted(l, o, "k")
    return j.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("x"), 1).alias("revenue"))


def sketch_errors(spark, d):
    """Whether sketches of distinct tokens, of quantiles and of frequent values are as near to the exact values as they promise."""
    docs = table(spark, d, "documents")
    return sketches.errors(docs.select(F.explode(tables.tokens(F.col("text"))).alias("w")), docs.select(F.col("n_chars").cast("double").alias("x")))


def sample_by_lang(spark, d):
    """A Bernoulli draw by language, by the id's hash, which any engine repeats; shares of 0.5, 0.25 and none."""
    u = F.conv(F.substring(F.md5(F.concat(F.lit("7:"), F.col("doc_id").cast("string"))), 1, 8), 16, 10).cast("double") / float(2**32)
    share = F.when(F.col("lang") == "en", 0.5).when(F.col("lang") == "de", 0.25).otherwise(0.0)
    return table(spark, d, "documents").filter(u < share).select("doc_id", "lang")


def observed_counts(spark, d):
    """Rows that passed a filter, counted while the query ran, beside its result's own count."""
    from pyspark.sql import Observation

    seen = Observation()
    docs = table(spark, d, "documents").select("doc_id", "n_chars").repartitionByRange(4, "n_chars")
    kept = docs.filter("n_chars > 1000").observe(seen, F.count("*").alias("n"), F.max("n_chars").alias("most"))
    own = kept.count()
    return spark.createDataFrame([(seen.get["n"], seen.get["most"], own)], "observed long, most long, n long")


def paged_candidates(spark, d):
    """The candidates' draw from a source of pages, the hundred smallest keys: the pages that the table's ids lie in, and of their ids those of the table."""
    from ..sources import paged

    ids, page = table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("sample_id")), 10  # of 2 ** 10 ids
    held = ids.filter("sample_id is not null").select(F.call_function("shiftright", F.col("sample_id"), F.lit(page)).alias("p")).distinct().orderBy("p").toPandas()["p"]  # a number a page
    spark.dataSource.register(paged.CandidatePages)
    drawn = spark.read.format("candidate_pages").option("page", 1 << page).option("pages", ",".join(map(str, held)) or "none").load()
    return drawn.join(ids, "sample_id", "left_semi").orderBy("key", "sample_id").limit(100).select("sample_id")


def sinks_roundtrip(spark, d):
    """Documents written by source and language, and edges in buckets; read back with the partitions pruned and counted."""
    from ..sinks import tables as sinks

    at = new_folder(spark, "sinks")
    sinks.by_columns(table(spark, d, "documents").select("doc_id", "source", "lang"), f"{at}/docs", ["source", "lang"])
    back = spark.read.parquet(f"{at}/docs").filter("lang = 'en'").groupBy("source").agg(F.count("*").alias("n"))
    return back.select(F.col("source").cast("string").alias("source"), "n")


def plan_counters(spark, d):
    """What a join's own counters say beside what they must: rows that met, and whether bytes were shuffled."""
    from ..operators.counters import plan_metrics

    j = table(spark, d, "lineitem").select("l_orderkey").hint("merge").join(table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey")
    told = plan_metrics(j)
    rows = max(x["value"] for x in told if x["metric"] == "number of output rows" and "Join" in x["node"])
    moved = sum(x["value"] for x in told if x["metric"] == "shuffle bytes written")
    return spark.createDataFrame([(int(rows), moved > 0)], "joined long, shuffled boolean")


QUERIES = [
    corpus_filter, feature_projection, dedupe_exact, leak_free_documents, pages_text_length, io_roundtrip_count, events_json_stats, join_broadcast, join_sortmerge,
    join_shufflehash, pool_minus_chosen, theta_pairs, score_band_pairs, history_in_interval, asof_last_score, lateral_topk, vocab_stats, loss_percentiles, mix_rollup,
    mix_cube, mix_grouping_sets, mix_pivot, score_deltas, moving_score, range_frame_score, topk_global, topk_per_source, stratified_quota, picks_union, picks_intersect,
    picks_except, fn_string, fn_date, fn_math, fn_array, fn_map, fn_json, vector_functions, weighted_sample, udf_rouge, udaf_vector_mean, udtf_tokens, answer_fallback,
    win_tumbling, win_sliding, win_session, sql_surface, join_null_safe, join_salted, sketch_errors, sample_by_lang, observed_counts, paged_candidates, sinks_roundtrip, plan_counters,
]
