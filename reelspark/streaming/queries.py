"""Growing specs and telemetry as streams. Every query runs to the end of what is there (AvailableNow)
into a table in the shared folder, which it returns; checkpoints make a restart exact."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.registry import query
from reelspark.session import table
from reelspark.sources.io import shared_folder

_US = "epoch_us(ts)"


def pushes(spark: SparkSession, sf_dir: str, files: int = 4, closing: bool = False) -> DataFrame:
    """The push log as a stream of files in order: spec_id, ord, frames, ts (a zoned timestamp; a watermark needs one).

    ``closing``: two much later pushes of no spec follow in batches of their own: the first moves the watermark past all that was pushed, the
    second gives the batch in which windows of append mode close and their state goes (its own windows stay open)."""
    folder, e = shared_folder(spark, "pushes"), table(spark, sf_dir, "events")
    end = e.agg((F.max("event_id") + 1).alias("n"), F.max("ts").alias("ts")).first()
    parts = [e.where(F.expr(f"event_id * {files} div {end['n']}") == k) for k in range(files)] if end["n"] else [e]
    if closing and end["n"]:
        parts += [e.limit(1).select(F.lit(-k).cast("bigint").alias("event_id"), (F.lit(end["ts"]) + F.expr("interval 60 days")).alias("ts"), F.lit(-1).cast("bigint").alias("user_id"), F.lit("close").alias("event_type"), F.lit(0.0).alias("value"), F.lit('{"k": -1}').alias("props")) for k in (1, 2)]
    for part in parts:  # one job after another, as the source reads files by age
        part.select(*e.columns).coalesce(1).write.mode("append").parquet(folder)
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1 if closing else 2).parquet(folder)
    return s.select(F.col("user_id").alias("spec_id"), F.col("event_id").alias("ord"), (F.get_json_object("props", "$.k").cast("bigint") + 1).alias("frames"), F.col("ts").cast("timestamp").alias("ts"), "event_type", "value")


def settled(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream to its end. Append: each batch is a folder of its own, overwritten if retried; complete: the last batch counts."""
    spark = stream.sparkSession
    path = shared_folder(spark, "stream")

    def keep(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/out/" + (f"batch={batch}" if mode != "complete" else "all"))

    q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    out = spark.read.schema(stream.schema).parquet(f"{path}/out/" + ("all" if mode == "complete" else ""))
    return out.select(*stream.columns)


_BUCKET = "SELECT CAST(b AS BIGINT) AS start_us, count(*) AS n FROM ({0}) GROUP BY 1"


@query("st_tumbling", _BUCKET.format(f"SELECT {_US} // 7200000000 * 7200000000 AS b FROM events"))
def st_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = pushes(spark, sf_dir, closing=True).withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 hours")).agg(F.count("*").alias("n"))
    return settled(w.select(F.unix_micros("window.start").alias("start_us"), "n"), "append")


@query("st_sliding", _BUCKET.format(f"SELECT {_US} // 3600000000 * 3600000000 - h * 3600000000 AS b FROM events, range(6) r(h)"))
def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = pushes(spark, sf_dir, closing=True).withWatermark("ts", "1 hour").groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count("*").alias("n"))
    return settled(w.select(F.unix_micros("window.start").alias("start_us"), "n"), "append")


@query("st_session", f"WITH t AS (SELECT user_id, {_US} AS us, {_US} - lag({_US}) OVER (PARTITION BY user_id ORDER BY {_US}) AS gap FROM events), s AS (SELECT user_id, us, sum(CASE WHEN gap IS NULL OR gap >= 21600000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY us) AS k FROM t) SELECT user_id AS spec_id, min(us) AS start_us, max(us) + 21600000000 AS end_us, count(*) AS n FROM s GROUP BY user_id, k")
def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a spec end six hours after its last push; then its store can be cleaned."""
    w = pushes(spark, sf_dir, closing=True).withWatermark("ts", "1 hour").groupBy("spec_id", F.session_window("ts", "6 hours").alias("s")).agg(F.count("*").alias("n"))
    return settled(w.select("spec_id", F.unix_micros("s.start").alias("start_us"), F.unix_micros("s.end").alias("end_us"), "n"), "append")


@query("st_watermark_late")
def st_watermark_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pushes out of order within the watermark are counted; append mode emits a window once it is closed."""
    s = pushes(spark, sf_dir).withColumn("ts", F.when(F.col("ord") % 7 == 3, F.col("ts") - F.expr("interval 90 minutes")).otherwise(F.col("ts")))
    w = s.withWatermark("ts", "2 hours").groupBy(F.window("ts", "2 hours")).agg(F.count("*").alias("n"))
    return settled(w.select(F.unix_micros("window.start").alias("start_us"), "n"), "append")


@query("st_watermark_dropped", f"WITH e AS (SELECT {_US} - CASE WHEN event_id % 7 = 3 THEN 864000000000 ELSE 0 END AS us, event_id * 4 // (SELECT max(event_id) + 1 FROM events) AS f FROM events), m AS (SELECT f, max(us) AS top FROM e GROUP BY f), x AS (SELECT us, (SELECT max(top) FROM m WHERE m.f < e.f - 1) - 7200000000 AS mark FROM e), k AS (SELECT mark IS NULL OR us // 7200000000 * 7200000000 + 7200000000 > mark AS kept FROM x) SELECT count(*) AS sent, count(*) FILTER (kept) AS counted, count(*) FILTER (NOT kept) AS dropped FROM k")
def st_watermark_dropped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every seventh push comes ten days late; those whose window was closed by the watermark are dropped, and counted here. Late rows meet
    the watermark of the batch before, which knows the files up to the last but one."""
    s = pushes(spark, sf_dir, closing=True).withColumn("ts", F.when(F.pmod("ord", F.lit(7)) == 3, F.col("ts") - F.expr("interval 10 days")).otherwise(F.col("ts")))
    w = s.withWatermark("ts", "2 hours").groupBy(F.window("ts", "2 hours")).agg(F.count("*").alias("n"))
    counted = settled(w.select("n"), "append").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("counted"))
    sent = table(spark, sf_dir, "events").count()
    return counted.select(F.lit(sent).cast("bigint").alias("sent"), "counted", (F.lit(sent) - F.col("counted")).alias("dropped"))


@query("st_dedup", "SELECT user_id AS spec_id, event_id AS ord FROM events")
def st_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every seventh push is sent twice; one of each remains."""
    s = pushes(spark, sf_dir).withColumn("copy", F.explode(F.when(F.col("ord") % 7 == 0, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))))
    once = s.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["spec_id", "ord"])
    return settled(once.select("spec_id", "ord"), "append")


@query("st_stream_static", "SELECT e.event_id AS ord, c_mktsegment AS segment FROM events e JOIN customer ON c_custkey = e.user_id")
def st_stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pushes checked against a catalogue that does not move."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("spec_id"), F.col("c_mktsegment").alias("segment"))
    return settled(pushes(spark, sf_dir).join(c, "spec_id").select("ord", "segment"), "append")


@query("st_stream_stream", f"WITH m AS (SELECT user_id, event_id, {_US} AS us FROM events WHERE event_type = 'click'), r AS (SELECT user_id, event_id, {_US} AS us FROM events WHERE event_type = 'error') SELECT m.event_id AS manifest, r.event_id AS request FROM m JOIN r ON m.user_id = r.user_id AND r.us >= m.us AND r.us <= m.us + 3600000000")
def st_stream_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Playlist updates with the segment requests of the hour after; both sides have watermarks and the bound ends their state."""
    m = pushes(spark, sf_dir).where("event_type = 'click'").select(F.col("spec_id").alias("a"), F.col("ord").alias("manifest"), F.col("ts").alias("t1")).withWatermark("t1", "40 days")
    r = pushes(spark, sf_dir).where("event_type = 'error'").select(F.col("spec_id").alias("b"), F.col("ord").alias("request"), F.col("ts").alias("t2")).withWatermark("t2", "40 days")
    on = F.expr("a = b AND t2 >= t1 AND t2 <= t1 + interval 1 hour")
    return settled(m.join(r, on).select("manifest", "request"), "append")


@query("st_outputs")
def st_outputs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that each output mode emits for one aggregation, and its total."""
    out = None
    for mode in ("append", "update", "complete"):
        w = pushes(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "12 hours")).agg(F.count("*").alias("n"))
        rows = settled(w.select(F.unix_micros("window.start").alias("start_us"), "n"), mode)
        one = rows.agg(F.lit(mode).alias("mode"), F.count("*").alias("rows"), F.sum("n").alias("total"))
        out = one if out is None else out.unionByName(one)
    return out


_PER_SPEC = "SELECT user_id AS spec_id, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT) + 1) AS BIGINT) AS frames, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT) + 1) // 60 AS BIGINT) AS segments FROM events GROUP BY 1"


@query("st_batch_equiv", _PER_SPEC)
def st_batch_equiv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals as they grow: each batch gives the specs that it touched, so output shrinks with the batch; a spec's last total is its greatest."""
    g = pushes(spark, sf_dir).groupBy("spec_id").agg(F.sum("frames").alias("frames"))
    last = settled(g.select("spec_id", "frames"), "update").groupBy("spec_id").agg(F.max("frames").alias("frames"))
    return last.select("spec_id", "frames", F.expr("frames div 60").alias("segments"))


def manifest_processor():
    """State per spec: frames so far. Emits a row for each segment that a batch completes."""
    from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

    class Manifest(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.frames = handle.getValueState("frames", "n bigint")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
            before = self.frames.get()[0] if self.frames.exists() else 0
            now = before + sum(int(r["frames"].sum()) for r in rows)
            self.frames.update((now,))
            segs = list(range(before // 60, now // 60))
            yield pd.DataFrame({"spec_id": [key[0]] * len(segs), "seg": segs}).astype("int64")

        def close(self) -> None:
            pass

    return Manifest()


@query("st_stateful", f"WITH p AS ({_PER_SPEC}) SELECT spec_id, unnest(range(segments)) AS seg FROM p")
def st_stateful(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Playlist rows as they come to be, from state kept per spec."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        s = pushes(spark, sf_dir).select("spec_id", "frames").groupBy("spec_id").transformWithStateInPandas(manifest_processor(), "spec_id bigint, seg bigint", "append", "none")
        return settled(s, "append")
    finally:
        spark.conf.set(key, before)


@query("stream_files", "SELECT count(*) AS n, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT) + 1) AS BIGINT) AS frames FROM events")
def stream_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = settled(pushes(spark, sf_dir).select("ord", "frames"), "append")
    return rows.agg(F.count("*").alias("n"), F.sum("frames").alias("frames"))


@query("sink_stream", "SELECT user_id AS spec_id, count(*) AS n FROM events GROUP BY 1")
def sink_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pushes into a store by batch id: a batch that is written again replaces itself."""
    return settled(pushes(spark, sf_dir).select("spec_id", "ord"), "append").groupBy("spec_id").agg(F.count("*").alias("n"))
