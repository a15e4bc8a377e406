"""Score readings as a stream: file source, watermark, windows, de-duplication, stateful drift, and updates per micro-batch."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str, per_trigger: int = 8) -> DataFrame:
    """Event files as they come; times are cast, since a watermark needs a zoned timestamp. path: a folder, or one file."""
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", "*.parquet").parquet(path if not name.endswith(".parquet") else f"{folder}/[e]vents.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def daily(stream: DataFrame, late: str = "1 day", slide: str | None = None, span: str = "1 day") -> DataFrame:
    """Tumbling or sliding windows; readings later than the watermark are dropped and counted in the progress."""
    w = F.window("ts", span, slide) if slide else F.window("ts", span)
    return stream.withWatermark("ts", late).groupBy(w).agg(F.count("*").alias("n"), F.round(F.avg("value"), 5).alias("mean"))


def once(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """Readings without replays."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drift_of(scores: list[float], decay_rate: float = 0.99) -> float:
    """As the batch statistic: decayed change against the last score, relative to it; 0 where that is 0 and nothing changed, else not a number."""
    now, top = scores[-1], len(scores) - 1
    w = [decay_rate ** (top - i) for i in range(len(scores))]
    change = sum(a * abs(s - now) for a, s in zip(w, scores, strict=True))
    if abs(now) <= 1e-12:
        return 0.0 if change <= 1e-12 else float("nan")
    return change / (sum(w) * now)


def drifts(readings: DataFrame, decay_rate: float = 0.99) -> DataFrame:
    """(sample_id, n, drift) of each row's readings so far, by arbitrary state; readings: (sample_id, step, score)."""
    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        past = list(state.get[0]) if state.exists else []
        new = pd.concat(list(batches)).sort_values("step")
        past = [*past, *new["score"].tolist()]
        state.update((past,))
        yield pd.DataFrame({"sample_id": [key[0]], "n": [len(past)], "drift": [drift_of(past, decay_rate)]})

    return readings.groupBy("sample_id").applyInPandasWithState(step, "sample_id long, n long, drift double", "scores array<double>", "update", GroupStateTimeout.NoTimeout)


def intervals(readings: DataFrame, late: str = "1 day", quiet_ms: int = 86_400_000, decay_rate: float = 0.99) -> DataFrame:
    """(sample_id, n, drift) of each row's interval, told when event time has passed its last reading by ``quiet_ms`` and the
    watermark; state is kept only for open intervals. readings: (sample_id, ts, step, score)."""
    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            steps, past = (list(x) for x in state.get[:2])
            state.remove()
            order = [s for _, s in sorted(zip(steps, past, strict=True))]
            yield pd.DataFrame({"sample_id": [key[0]], "n": [len(order)], "drift": [drift_of(order, decay_rate)]})
            return
        steps, past, last = (list(state.get[0]), list(state.get[1]), state.get[2]) if state.exists else ([], [], 0)
        for batch in batches:
            steps += batch["step"].tolist()
            past += batch["score"].tolist()
            last = max(last, int(batch["ts"].max().timestamp() * 1000))
        state.update((steps, past, last))
        state.setTimeoutTimestamp(max(last + quiet_ms, state.getCurrentWatermarkMs() + 1))

    schema, kept = "sample_id long, n long, drift double", "steps array<long>, scores array<double>, last long"
    return readings.withWatermark("ts", late).groupBy("sample_id").applyInPandasWithState(step, schema, kept, "append", GroupStateTimeout.EventTimeTimeout)


def with_nodes(readings: DataFrame, nodes: DataFrame) -> DataFrame:
    """Readings with what the graph knows of their rows: a stream meets a table, which is read as it is for each micro-batch."""
    return readings.join(nodes, "sample_id", "left")


def with_extractions(readings: DataFrame, extractions: DataFrame, late: str = "1 day", within: str = "1 hour") -> DataFrame:
    """Readings with the re-extractions of the same row that came at most so long after: two streams, whose watermarks and time
    bound say how long either side is kept. readings: (sample_id, ts, ...); extractions: (sample_id, ts, score_new)."""
    a = readings.withWatermark("ts", late).alias("a")
    b = extractions.withColumnsRenamed({"sample_id": "_id", "ts": "ts_new"}).withWatermark("ts_new", late).alias("b")
    on = (F.col("a.sample_id") == F.col("b._id")) & (F.col("ts_new") >= F.col("ts")) & (F.col("ts_new") <= F.col("ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).drop("_id")


def on_batch(stream: DataFrame, act: Callable[[DataFrame, int], None], checkpoint: str):
    """Runs an action, such as a check-and-update, on every micro-batch of what is there now."""
    return stream.writeStream.foreachBatch(act).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def daily_counts(spark: SparkSession, path: str, at: str) -> DataFrame:
    """Reads what is there as a stream, keeps every micro-batch's full counts in files, and returns the last ones."""
    counts = source(spark, path).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"), F.round(F.avg("value"), 5).alias("mean"))
    rows = counts.select(F.col("window.start").cast("string").substr(1, 10).alias("day"), "n", "mean")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={number}")

    query = rows.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.parquet(f"{at}/out")
    return out.join(out.agg(F.max("batch").alias("batch")), "batch").select("day", "n", "mean")
