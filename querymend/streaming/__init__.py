"""Streaming operators and the stream service. A replay reads files that are
there with ``availableNow`` and writes every batch to Parquet in the shared
folder; results are read from that, never held in the driver."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..shared import workspace

END = "end of stream"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a stream; a watermark needs a time-zoned timestamp. The path
    is given to the reader as a pattern, as a file source takes a folder."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]").withColumn("ts", F.col("ts").cast("timestamp"))


def closed(stream: DataFrame, days: int = 1000) -> DataFrame:
    """The stream and, for one of its rows, a marker long after all others: its
    time moves the watermark past every window, as live traffic would."""
    marker = stream.where("event_id = 0").withColumn("ts", F.col("ts") + F.expr(f"INTERVAL {days} DAYS")).withColumn("event_type", F.lit(END))
    return stream.unionByName(marker)


def replay(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there; the rows that it emitted. A batch
    that is run again after a failure writes the same folder again."""
    spark, folder = df.sparkSession, workspace(df.sparkSession, "stream")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{folder}/out/part={number}")

    q = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    schema = T.StructType([*df.schema.fields, T.StructField("batch", T.IntegerType())])
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{folder}/out")


def s_tumble(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by type and day; a window comes out once, when it is closed."""
    w = closed(events(spark, sf_dir)).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return replay(w).where(F.col("event_type") != END).select(F.date_format("w.start", "yyyy-MM-dd").alias("d"), "event_type", "n")


def s_slide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in windows of two days that start every day."""
    w = closed(events(spark, sf_dir)).withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 days", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return replay(w).where(F.col("event_type") != END).groupBy(F.date_format("w.start", "yyyy-MM-dd").alias("d")).agg(F.sum("n").alias("n"))


def s_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user: runs of events less than six hours apart."""
    w = closed(events(spark, sf_dir)).withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"), F.max("event_type").alias("t"), F.min("ts").alias("first"))
    done = replay(w).where(F.col("first") < F.lit("2200-01-01"))
    return done.where((F.col("t") != END) | (F.col("n") > 1)).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"), F.max("n").alias("longest"))


def s_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = events(spark, sf_dir)
    return replay(e.unionAll(e).withWatermark("ts", "100 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")).drop("batch")


def s_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sign-ups with the errors of the same user in the next hour; both sides'
    state is bounded by their watermarks."""
    a = events(spark, sf_dir).where("event_type = 'signup'").select(F.col("event_id").alias("s"), F.col("user_id").alias("u"), F.col("ts").alias("t0")).withWatermark("t0", "1 hour")
    b = events(spark, sf_dir).where("event_type = 'error'").select(F.col("event_id").alias("e"), "user_id", "ts").withWatermark("ts", "1 hour")
    joined = a.join(b, F.expr("u = user_id AND ts > t0 AND ts <= t0 + INTERVAL 60 MINUTES"))
    return replay(joined.select("s", "e")).drop("batch")


def s_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors of each user, as kept state; a user's count of the last batch
    that has rows of it is the final one."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Errors(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.count = handle.getValueState("n", "n long")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
            n = (self.count.get()[0] if self.count.exists() else 0) + sum(int((f["event_type"] == "error").sum()) for f in rows)
            self.count.update((n,))
            yield pd.DataFrame({"user_id": [key[0]], "errors": [n]})

        def close(self) -> None:
            pass

    provider = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(provider)
    spark.conf.set(provider, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        s = events(spark, sf_dir).select("user_id", "event_type").groupBy("user_id")
        out = replay(s.transformWithStateInPandas(Errors(), "user_id long, errors long", "Update", "None"), "update")
    finally:
        spark.conf.set(provider, before)
    return out.groupBy("user_id").agg(F.max_by("errors", "batch").alias("errors"))


def serve(log: DataFrame, catalog, model, sink: str, checkpoint: str, cfg=None, examples=()) -> None:
    """The service: a stream of (ts, question_id, candidate_id, question, sql) is
    cleared of repeats of one text within the watermark, mended as it comes and
    appended to Parquet, a folder a batch, so that a batch that is run again
    replaces itself."""
    from ..mend import mend

    fresh = log.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["question", "sql"])
    put = lambda batch, number: mend(batch, catalog, model, cfg, examples).write.mode("overwrite").parquet(f"{sink}/part={number}")
    q = fresh.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


QUERIES = {f.__name__: f for f in (s_tumble, s_slide, s_session, s_dedup, s_join, s_state)}
ORACLES = {
    "s_tumble": "SELECT strftime(ts, '%Y-%m-%d') AS d, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "s_slide": "SELECT strftime(d, '%Y-%m-%d') AS d, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM events) GROUP BY 1",
    "s_session": "SELECT user_id, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS n, max(n) AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s) GROUP BY user_id",
    "s_dedup": "SELECT event_id FROM events",
    "s_join": "SELECT a.event_id AS s, b.event_id AS e FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE WHERE a.event_type = 'signup' AND b.event_type = 'error'",
    "s_state": "SELECT user_id, count(*) FILTER (event_type = 'error') AS errors FROM events GROUP BY 1",
}
