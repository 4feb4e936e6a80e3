"""Streams of records: profiles by window, drift of missing rates, duplicates, matching.

Every operator takes a streaming or a static DataFrame of events, so that the
stream can be held against the batch.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.operators import match
from linkgraph.sources.shared import shared_folder

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def _timed(events: DataFrame, late: str) -> DataFrame:
    return events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)


def window_profile(events: DataFrame, size: str = "6 hours", late: str = "10 days") -> DataFrame:
    """Rows, missing values and spread of ``value`` by tumbling window."""
    out = _timed(events, late).groupBy(F.window("at", size).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("value").isNull().cast("long")).alias("missing"), F.min("value").alias("low"), F.max("value").alias("high"))
    return out.select(F.unix_seconds("w.start").alias("start"), "n", "missing", "low", "high")


def sliding_counts(events: DataFrame, size: str = "6 hours", slide: str = "2 hours", late: str = "10 days") -> DataFrame:
    out = _timed(events, late).groupBy(F.window("at", size, slide).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 days") -> DataFrame:
    out = _timed(events, late).groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return out.select("user_id", F.unix_seconds("w.start").alias("start"), "n")


def drift_alarm(profiles: DataFrame, warn: float = 0.2, alarm: float = 0.3) -> DataFrame:
    """Windows whose missing rate leaves the range in which matching degrades gently."""
    rate = F.col("missing") / F.col("n")
    return profiles.withColumn("rate", F.round(rate, 6)).withColumn("state", F.when(rate >= alarm, "alarm").when(rate >= warn, "warning").otherwise("fine"))


def without_repeats(events: DataFrame, late: str = "10 days") -> DataFrame:
    """Events once each, as far back as the watermark reaches."""
    timed = _timed(events, late)
    return timed.dropDuplicatesWithinWatermark(["event_id"]).drop("at") if events.isStreaming else timed.dropDuplicates(["event_id"]).drop("at")


def running_profile(events: DataFrame) -> DataFrame:
    """Count and sum of values by user, kept in state across batches (streams only)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key, frames, state: GroupState):
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [round(total, 2)]})

    return events.select("user_id", "value").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)


def match_batch(token_vectors: DataFrame, known: DataFrame, tau: float, sink: Callable[[DataFrame, int], None], dim: int):
    """A foreachBatch function: new records get vectors from known tokens, and are matched.

    ``token_vectors`` is (tok, vec), ``known`` is (key, vec) of the other side;
    batches have (rid, tok).  No model is learnt anew.
    """
    from linkgraph.operators.embed import record_vectors

    def run(batch: DataFrame, number: int) -> None:
        weights = token_vectors.select("tok", F.lit(1.0).alias("w"))
        new = record_vectors(batch.groupBy("rid", "tok").agg(F.count(F.lit(1)).alias("mult")), token_vectors, weights, dim).withColumnRenamed("rid", "key")
        pairs = match.candidates_lsh(new, known, dim)
        sink(match.select_matches(match.cosine_pairs(pairs, new, known), "best_left", tau), number)

    return run


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what is there now and returns what it wrote: files in the shared folder."""
    spark, where = stream.sparkSession, f"{shared_folder(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    spark.createDataFrame([], stream.schema).write.parquet(f"{where}/rows")

    def write(batch: DataFrame, number: int) -> None:
        # a repeated batch writes the same folder again
        part = f"{where}/rows" if mode == "complete" else f"{where}/rows/batch={number}"
        batch.write.mode("overwrite").parquet(part)

    query = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).option("recursiveFileLookup", "true").parquet(f"{where}/rows")


def _worsening(events: DataFrame) -> DataFrame:
    """Events whose values go missing on some days more than on others."""
    gap = F.pmod("event_id", F.lit(10)) < F.pmod(F.dayofmonth("ts"), F.lit(6))
    return events.withColumn("value", F.when(~gap, F.col("value")))


QUERIES = {
    "stream_profile": (lambda s, d: drain(window_profile(event_stream(s, d))), "SELECT CAST(floor(epoch(ts) / 21600) * 21600 AS BIGINT) AS start, count(*) AS n, CAST(sum(CAST(value IS NULL AS INT)) AS BIGINT) AS missing, min(value) AS low, max(value) AS high FROM events GROUP BY 1"),
    "stream_drift": (lambda s, d: drift_alarm(drain(window_profile(_worsening(event_stream(s, d))))).select("start", "rate", "state"), "WITH e AS (SELECT CAST(floor(epoch(ts) / 21600) * 21600 AS BIGINT) AS start, CAST(event_id % 10 < day(ts) % 6 AS INT) AS gap FROM events), w AS (SELECT start, sum(gap) / count(*) AS r FROM e GROUP BY 1) SELECT start, round(r, 6) AS rate, CASE WHEN r >= 0.3 THEN 'alarm' WHEN r >= 0.2 THEN 'warning' ELSE 'fine' END AS state FROM w"),
    "stream_sessions": (lambda s, d: drain(sessions(event_stream(s, d))), "WITH e AS (SELECT user_id, epoch(ts) AS t, CASE WHEN epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800 THEN 0 ELSE 1 END AS fresh FROM events), g AS (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS g FROM e) SELECT user_id, CAST(floor(min(t)) AS BIGINT) AS start, count(*) AS n FROM g GROUP BY user_id, g"),
    "stream_static": (lambda s, d: drain(event_stream(s, d).join(F.broadcast(s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")), "user_id").select("event_id", "c_mktsegment"), "append"), "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey"),
    "stream_sliding": (lambda s, d: drain(sliding_counts(event_stream(s, d))), "SELECT CAST((floor(epoch(ts) / 7200) - k) * 7200 AS BIGINT) AS start, event_type, count(*) AS n FROM events, range(3) t(k) GROUP BY 1, 2"),
    "stream_dedup": (lambda s, d: drain(without_repeats(event_stream(s, d)).select("event_id"), "append"), "SELECT DISTINCT event_id FROM events"),
    "stream_running": (lambda s, d: drain(running_profile(event_stream(s, d)), "update"), "SELECT user_id, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY 1"),
}
