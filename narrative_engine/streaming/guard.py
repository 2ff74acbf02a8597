"""The guard on a stream: windows of activity, explained, narrated, graded and guarded as in batch.

``events`` holds times without a zone; a stream's watermark needs instants, so they are cast first
(UTC).  Explanations use a card fitted in batch.  Every step after the windows is local to the row.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.plans.twins import guarded_days
from narrative_engine.shipping import ship
from narrative_engine.sources.tables import table
from narrative_engine.staging import kept_until_exit, shared_dir, staged

LATE = "2 days"


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a file stream with instants and a watermark."""
    schema = table(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", LATE)


def drained(df: DataFrame, mode: str = "complete", top: str | None = None) -> DataFrame:
    """The table that the stream leaves when all there is has been read.

    Appended rows go to files; complete and updated tables to a folder per micro-batch, which a batch
    that is run again replaces.  Of complete ones the last folder is the table; updated ones are
    returned from all batches, with ``batch``.
    """
    spark = df.sparkSession
    top = top or f"{shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    writer = df.writeStream.option("checkpointLocation", f"{top}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{top}/out").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{kept_until_exit(spark, top)}/out")
    seen: list[int] = []

    def sink(batch: DataFrame, batch_id: int) -> None:
        seen.append(batch_id)
        idempotent_sink(f"{top}/out")(batch, batch_id)

    writer.outputMode(mode).foreachBatch(sink).start().awaitTermination()
    kept_until_exit(spark, top)
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{top}/out/batch={max(seen)}") if seen else spark.createDataFrame([], df.schema)
    return spark.read.option("basePath", f"{top}/out").parquet(f"{top}/out")


def cents(c: str = "value"):
    return F.sum(F.floor(F.col(c) * 100 + 0.5).cast("bigint")).alias("cents")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = source(spark, sf_dir).groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), cents())
    return drained(rows).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("hour"), "event_type", "n", "cents")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = source(spark, sf_dir).groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return drained(rows).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = source(spark, sf_dir).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(rows).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = source(spark, sf_dir)
    rows = rows.unionByName(source(spark, sf_dir)).dropDuplicatesWithinWatermark(["event_id"]).select("event_id")
    return drained(rows, "append").agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("different"))


def guarded_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User days as they close: explanation, narrative, grades and what is shown."""
    from narrative_engine.operators import attribution as at
    from narrative_engine.operators import explanation as ex
    from narrative_engine.operators import grading as gr
    from narrative_engine.operators import writing as wr
    from narrative_engine.sources.tables import NUMERIC, features

    card = staged(at.fit_numeric(features(spark, sf_dir, "activity"), NUMERIC["activity"]))
    kind = lambda t: F.sum((F.col("event_type") == t).cast("int")).cast("decimal(18,4)")
    days = (
        source(spark, sf_dir).groupBy(F.window("ts", "1 day").alias("w"), "user_id")
        .agg(kind("click").alias("clicks"), kind("view").alias("views"), kind("error").alias("errors"), kind("signup").alias("signups"), kind("purchase").alias("purchases"), F.size(F.collect_set("props")).cast("decimal(18,4)").alias("distinct_props"))
        .withColumn("row_id", F.concat(F.col("user_id").cast("string"), F.lit("@"), F.date_format("w.start", "yyyy-MM-dd")))
    )
    rows = ex.top_contributions(at.attribute_additive(days, NUMERIC["activity"], (), card, None)).select("row_id", "expl")
    rows = rows.withColumn("text", wr.zero_shot(F.col("expl"))).withColumn("claims", gr.claims(F.col("text"), F.col("expl")))
    s = gr.conciseness(gr.word_count(F.col("text")), F.size("expl"), F.lit(30.0))
    rows = rows.withColumn("a", gr.accuracy(F.col("claims"))).withColumn("c", gr.completeness(F.col("claims"))).withColumn("total", F.lit(4.0) * F.col("a") + F.lit(2.0) * F.col("c") + s)
    return rows.withColumn("rejected", F.col("total") < 10.5).withColumn("shown", F.when(F.col("rejected"), gr.bar_view(F.col("expl"))).otherwise(F.col("text")))


def stream_guardrail(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = drained(guarded_stream(spark, sf_dir).select("row_id", "a", "c", "rejected"), "update")
    last = rows.groupBy("row_id").agg(F.max_by(F.struct("a", "c", "rejected"), "batch").alias("x"))
    return last.groupBy("x.a", "x.c", "x.rejected").agg(F.count("*").alias("n"))


def _folder_of(spark: SparkSession, parts: list[DataFrame]) -> str:
    """A folder that gets the parts as files, one after another, as a stream would see them arrive."""
    path = f"{shared_dir(spark).rstrip('/')}/arrivals-{uuid.uuid4().hex}"
    for part in parts:
        part.coalesce(1).write.mode("append").parquet(path)
    return kept_until_exit(spark, path)


def _arrivals(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", LATE)


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by day when the first day's come a second time, long after its window closed: they are dropped.

    A micro-batch drops what is late by the watermark of the one before it, so they come third.
    """
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    first, last = events.agg(F.min("ts"), F.max("ts")).first()
    middle = first + (last - first) / 2
    again = events.where(F.col("ts") < F.lit(first) + F.expr("INTERVAL 1 DAY"))
    path = _folder_of(spark, [events.where(F.col("ts") <= F.lit(middle)), events.where(F.col("ts") > F.lit(middle)), again])
    rows = _arrivals(spark, path, events.schema).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return drained(rows, "update").groupBy(F.date_format("w.start", "yyyy-MM-dd").alias("day")).agg(F.max("n").alias("n"))


def restarted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts by type from a stream that stops after half of the events and goes on from its checkpoint; a batch written twice counts once."""
    events = table(spark, sf_dir, "events").select("event_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    path = _folder_of(spark, [events.where("event_id % 2 = 0")])
    top = f"{shared_dir(spark).rstrip('/')}/restart-{uuid.uuid4().hex}"
    count = lambda: _arrivals(spark, path, events.schema).select("event_id", "event_type")
    drained(count(), "update", top)
    events.where("event_id % 2 = 1").coalesce(1).write.mode("append").parquet(path)
    rows = drained(count(), "update", top)
    idempotent_sink(f"{top}/out")(staged(rows.where("batch = 0").drop("batch")), 0)  # what a retry after a crash would do
    return spark.read.option("basePath", f"{top}/out").parquet(f"{top}/out").groupBy("event_type").agg(F.count("*").alias("n"))


def near_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-stream join: events of a user within five minutes of one of the user's errors, per user."""
    a = source(spark, sf_dir).where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("at"))
    b = source(spark, sf_dir).select("event_id", "user_id", "ts")
    near = F.expr("user_id = u AND ts >= at - INTERVAL 5 MINUTES AND ts <= at + INTERVAL 5 MINUTES AND event_id <> error_id")
    return drained(a.join(b, near).select("user_id", "event_id", "error_id"), "append").groupBy("user_id").agg(F.count("*").alias("n"))


def _running(key, batches, state):
    """Count and sum so far of one event type, kept between micro-batches."""
    import pandas as pd

    n, total = state.get if state.exists else (0, 0)
    for pdf in batches:
        n, total = n + len(pdf), total + int((pdf["value"] * 100 + 0.5).floordiv(1).sum())
    state.update((n, total))
    yield pd.DataFrame({"event_type": [key[0]], "n": [n], "cents": [total]})


def running_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Custom state: a running count and sum per event type; the last state is the batch result."""
    ship(spark)
    rows = source(spark, sf_dir).select("event_type", "value").groupBy("event_type")
    out = rows.applyInPandasWithState(_running, "event_type string, n long, cents long", "n long, cents long", "update", "NoTimeout")
    return drained(out, "update").groupBy("event_type").agg(F.max("n").alias("n"), F.max_by("cents", "n").alias("cents"))


class _Drift:
    """State of one event type: count and sum so far; each micro-batch tells how far its mean lies from the one before."""

    def init(self, handle) -> None:
        self.seen = handle.getValueState("seen", "n long, cents long")

    def handleInputRows(self, key, rows, timerValues):
        import pandas as pd

        n, cents = self.seen.get() if self.seen.exists() else (0, 0)
        more, plus = 0, 0
        for pdf in rows:
            more, plus = more + len(pdf), plus + int((pdf["value"] * 100 + 0.5).floordiv(1).sum())
        self.seen.update((n + more, cents + plus))
        drift = (cents + plus) / (n + more) - cents / n if n else 0.0
        yield pd.DataFrame({"event_type": [key[0]], "n": [n + more], "cents": [cents + plus], "drift": [drift]})

    def close(self) -> None:
        pass


def drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Custom state by the arbitrary-state operator: running totals by event type and how their mean drifts between micro-batches."""
    from pyspark.sql.streaming.stateful_processor import StatefulProcessor

    ship(spark)
    key, before = "spark.sql.streaming.stateStore.providerClass", spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")  # the operator asks for it
    events = table(spark, sf_dir, "events").select("event_type", "value", F.col("ts").cast("timestamp").alias("ts"))
    middle = events.agg(F.percentile_approx(F.col("ts").cast("double"), 0.5)).first()[0]
    path = _folder_of(spark, [events.where(F.col("ts").cast("double") <= middle), events.where(F.col("ts").cast("double") > middle)])
    kind = type("Drift", (_Drift, StatefulProcessor), {})
    rows = _arrivals(spark, path, events.schema).groupBy("event_type").transformWithStateInPandas(kind(), "event_type string, n long, cents long, drift double", "Update", "None")
    try:
        out = drained(rows, "update")
    finally:
        spark.conf.set(key, before) if before else spark.conf.unset(key)
    return out.groupBy("event_type").agg(F.max("n").alias("n"), F.max_by("cents", "n").alias("cents"))


def idempotent_sink(path: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch writer: a batch that is run again replaces its own folder."""
    return lambda batch, batch_id: batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")


QUERIES = {
    "stream_tumbling": tumbling, "stream_sliding": sliding, "stream_session": sessions, "stream_dedup": deduplicated, "stream_guardrail": stream_guardrail, "stream_join": near_errors, "stream_stateful": running_totals,
    "stream_late": late_rows, "stream_restart": restarted, "stream_drift": drift,
}
ORACLES = {
    "stream_tumbling": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS hour, event_type, count(*) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT strftime(h, '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY 1",
    "stream_session": "WITH g AS (SELECT user_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events) SELECT user_id, CAST(sum(fresh) AS BIGINT) AS sessions, count(*) AS events FROM g GROUP BY user_id",
    "stream_join": "SELECT b.user_id, count(*) AS n FROM events a JOIN events b ON b.user_id = a.user_id AND b.ts >= a.ts - INTERVAL 5 MINUTE AND b.ts <= a.ts + INTERVAL 5 MINUTE AND b.event_id <> a.event_id WHERE a.event_type = 'error' GROUP BY b.user_id",
    "stream_stateful": "SELECT event_type, count(*) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY event_type",
    "stream_guardrail": guarded_days(),
    "stream_late": "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1",
    "stream_drift": "SELECT event_type, count(*) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY event_type",
    "stream_restart": "SELECT event_type, count(*) AS n FROM events GROUP BY event_type",
    "stream_dedup": "SELECT count(*) AS n, count(DISTINCT event_id) AS different FROM events",
}
