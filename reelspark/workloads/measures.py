"""Measures by name, the variants that only differ in a setting, and the checked ingestion of pushes."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.engine import kernels
from reelspark.engine.core import EngineConfig, simulate
from reelspark.model.expr import ref
from reelspark.registry import ORACLES, query
from reelspark.session import table
from reelspark.sources import io
from reelspark.workloads import access, delivery, lifting, rendering, search, studies
from reelspark.workloads.clips import TASKS, pixels_sql, task_sources
from reelspark.workloads.filters import _L, _Y, _each, _sql

query("base_full_engine", pixels_sql("corner"))(lambda spark, sf_dir: rendering._digest(rendering.rendered(spark, sf_dir, "corner")))
query("first_segment", pixels_sql("box_label", "o_orderkey BETWEEN 0 AND 47"))(delivery.render_segment)


@query("base_reorder_stream")
def base_reorder_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Display-order decoders with a buffer each against emission in decode order: frames waiting in buffers, and ticks."""
    rows = []
    for name, schedule in access.dense(spark, sf_dir).items():
        for emit in ("decode", "display"):
            s = simulate(schedule, 60, None, EngineConfig(pool=64, window=50, decoders=4, filters=4, emit=emit), b_run=2)
            rows.append((name, emit, s["frames_decoded"], s["peak_pool"], s["peak_reorder"], s["ticks"]))
    return spark.createDataFrame(rows, "pattern string, emit string, frames_decoded bigint, peak_pool bigint, peak_reorder bigint, ticks bigint")


@query("base_no_abandon")
def base_no_abandon(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Abandonment on and off: without it scattered access stops for good at a small pool."""
    from reelspark.engine.core import EngineStuck

    rows = []
    for name, schedule in access.dense(spark, sf_dir).items():
        for on in (True, False):
            try:
                s = simulate(schedule, 60, None, EngineConfig(pool=30, window=24, decoders=2, abandon=on))
                rows.append((name, on, True, s["frames_decoded"], s["ticks"]))
            except EngineStuck:
                rows.append((name, on, False, None, None))
    return spark.createDataFrame(rows, "pattern string, abandon boolean, finished boolean, frames_decoded bigint, ticks bigint")


_COUNTERS = {"m_frames_decoded": "frames_decoded", "m_gop_open": "gop_opens", "m_abandon": "abandons", "m_evict": "evictions", "m_drop": "drops", "m_stall": "stalls"}
for _name, _column in _COUNTERS.items():
    query(_name)(lambda spark, sf_dir, c=_column: rendering.m_stats(spark, sf_dir).groupBy("spec_id").agg(F.sum(c).alias(c), F.max(c).alias("most_in_a_segment")))


@query("m_pool_peak")
def m_pool_peak(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fullest pool in frames and in bytes, native and three-byte."""
    peak = rendering.m_stats(spark, sf_dir).groupBy("spec_id").agg(F.max("peak_pool").alias("frames"))
    return peak.withColumns({"native_bytes": F.col("frames") * 384, "bgr_bytes": F.col("frames") * 768})


@query("m_makespan")
def m_makespan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return access.w_threads(spark, sf_dir).select("pattern", "decoders", "filters", "ticks")


@query("m_peak_resident")
def m_peak_resident(spark: SparkSession, sf_dir: str) -> DataFrame:
    return studies.w_hue_scripts(spark, sf_dir).select("style", "gop_len", "peak_resident")


query("m_fps_by_res")(studies.w_resolution)
query("w_formats", ORACLES["m_conv_count"])(lifting.m_conv_count)
query("m_ttp")(studies.m_time_to_playback)


@query("m_speedup")
def m_speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Script seconds over the seconds of engine and first segment."""
    t = studies.m_time_to_playback(spark, sf_dir)
    base = t.where("kind = 'script'").select(F.col("seconds").alias("script_seconds"))
    return t.join(F.broadcast(base), F.lit(True)).select("kind", "seconds", F.round(F.col("script_seconds") / F.col("seconds"), 2).alias("speedup"))


@query("m_full_time")
def m_full_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds (measured) to render each annotation task in full; the first also writes the clip and the lists of detections that all read."""
    rows = []
    for task, recipe in TASKS.items():
        began = time.perf_counter()
        n = rendering.rendered(spark, sf_dir, recipe, "gop_exchange" if "mask" in recipe else "segment_local", stored=True).select("gen").count()
        rows.append((task, n, round(time.perf_counter() - began, 3)))
    return spark.createDataFrame(rows, "task string, frames bigint, seconds double")


@query("m_lift_time")
def m_lift_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds to replay a script without pixels, and to build the same kind of spec by join."""
    began = time.perf_counter()
    rows = [("replay", lifting.replayed_counter(spark, sf_dir).count(), round(time.perf_counter() - began, 3))]
    began = time.perf_counter()
    rows.append(("join", lifting.lift_relational(spark, sf_dir).count(), round(time.perf_counter() - began, 3)))
    return spark.createDataFrame(rows, "kind string, frames bigint, seconds double")


@query("m_seg_cache_hit", f"WITH {delivery._REQ} SELECT round(CAST(count(*) - count(DISTINCT (spec_id, seg)) AS DOUBLE) / count(*), 9) AS rate FROM req")
def m_seg_cache_hit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return delivery.segment_cache(spark, sf_dir).select(F.round(F.col("hits") / F.col("requests"), 9).alias("rate"))


@query("m_block_hit", io._BLOCKS + " SELECT round(CAST(count(*) - count(DISTINCT (source, block)) AS DOUBLE) / count(*), 9) AS rate FROM t")
def m_block_hit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return io.block_hit(spark, sf_dir).select(F.round(F.col("hits") / F.col("requests"), 9).alias("rate"))


_BLOCKS_BY = "SELECT CAST({b} AS BIGINT) AS block_bytes, count(*) AS requests, count(DISTINCT (source, block)) AS misses FROM (SELECT user_id AS source, unnest(range(lo // {b}, (lo + 41999) // {b} + 1)) AS block FROM a)"


@query("w_blockcache", "WITH a AS (SELECT user_id, (CAST(json_extract(props, '$.k') AS BIGINT) % 50) * 42000 AS lo FROM events) " + " UNION ALL ".join(_BLOCKS_BY.format(b=b) for b in (4096, 65536, 1048576)))
def w_blockcache(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Block touches of segment requests and their compulsory misses, by block size."""
    out = None
    for b in (4096, 65536, 1048576):
        per = io.block_touches(io.accesses(spark, sf_dir), b).groupBy("source", "block").agg(F.count("*").alias("n"))
        one = per.agg(F.lit(b).cast("bigint").alias("block_bytes"), F.sum("n").alias("requests"), F.count("*").alias("misses"))
        out = one if out is None else out.unionByName(one)
    return out


@query("sink_playlist", "SELECT 'coll_' || (o_custkey % 100) AS spec, 7 + 2 * ((count(*) + 59) // 60) AS lines, (count(*) + 59) // 60 AS segments FROM orders GROUP BY 1 UNION ALL SELECT 'main', 7 + 2 * ((count(*) + 47) // 48), (count(*) + 47) // 48 FROM orders")
def sink_playlist(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Playlists written as text, one file a spec, and read back: lines per spec."""
    path = io.shared_folder(spark, "playlists")
    lists = delivery.manifest_vod(spark, sf_dir).select(F.regexp_replace("spec_id", "/", "_").alias("spec"), F.col("text").alias("value"))
    lists.write.partitionBy("spec").text(path)
    return spark.read.text(path).groupBy("spec").agg(F.count("*").alias("lines"), F.count_if(F.col("value").startswith("#EXTINF")).alias("segments"))


# -- further filters -----------------------------------------------------------------------------------------


@query("f_identity", _sql(_L, "y, x"))
def f_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """References only: luma as it was."""
    return _each(spark, sf_dir, lambda f: kernels.apply_node("identity", [f], [], "")[1][0])


query("f_grid", ORACLES["w_sidebyside"])(search.w_sidebyside)


@query("f_circle", _sql(f"CASE WHEN (x - 8) * (x - 8) + (y - 7) * (y - 7) <= 25 AND (x - 8) * (x - 8) + (y - 7) * (y - 7) > 16 THEN ((66 * 30 + 129 * 20 + 25 * 10 + 128) >> 8) + 16 ELSE {_L} END", "y, x"))
def f_circle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A ring on the luma plane."""
    return _each(spark, sf_dir, lambda f: kernels.apply_node("circle", [kernels.pixfmt(f, "gray8")], [8, 7, 5, 10, 20, 30], "")[1][0])


@query("f_line", _sql(f"CASE WHEN x = y THEN ((66 * 30 + 129 * 20 + 25 * 10 + 128) >> 8) + 16 ELSE {_L} END", "y, x"))
def f_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The diagonal on the luma plane."""
    return _each(spark, sf_dir, lambda f: kernels.apply_node("line", [kernels.pixfmt(f, "gray8")], [0, 0, 15, 15, 10, 20, 30], "")[1][0])


_HEAT_V = _Y.format(x="x", y="y")


@query("f_heat", "WITH f AS (SELECT o_orderkey AS i, CAST(floor(o_totalprice / 1000.0) AS BIGINT) AS p FROM orders), v AS (SELECT i, x, y, " + _HEAT_V + " AS v FROM f, range(16) tx(x), range(16) ty(y)) SELECT i AS frame, md5(string_agg(concat_ws(',', (96 * least(255, greatest(0, 255 - 2 * v)) + 160 * v) >> 8, (96 * least(255, greatest(0, 255 - abs(2 * v - 255))) + 160 * v) >> 8, (96 * least(255, greatest(0, 2 * v - 255)) + 160 * v) >> 8), ',' ORDER BY y, x)) AS md5 FROM v GROUP BY i")
def f_heat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each frame's luma as a heat raster over its own grey picture."""

    def change(f):
        g = kernels.pixfmt(f, "gray8")
        return kernels.apply_node("heat", [kernels.pixfmt(g, "bgr24"), g], [96], "")[1][0]

    return _each(spark, sf_dir, change)


# -- checked ingestion ------------------------------------------------------------------------------------


@query("push_ingest", "SELECT user_id AS spec_id, count(*) FILTER (event_type <> 'error') AS accepted, count(*) FILTER (event_type = 'error') AS rejected FROM events GROUP BY 1")
def push_ingest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as pushed frames, those of type error with a reference outside the clip: what the store took and what it refused."""
    from reelspark.streaming.queries import pushes
    from reelspark.vod.stream import ingest

    path = io.shared_folder(spark, "ingest")
    idx = F.when(F.col("event_type") == "error", F.lit(1 << 40)).otherwise(F.pmod("ord", F.lit(100)))
    rows = pushes(spark, sf_dir).select(F.col("spec_id").cast("string").alias("spec_id"), F.col("ord").alias("gen"), F.expr("ord div 60").alias("seg"), F.array(ref("main", idx)).alias("nodes"))
    ingest(rows, task_sources(spark, sf_dir), path, f"{path}/state", (16, 16, "yuv420p")).awaitTermination()
    a = spark.read.parquet(f"{path}/specs").groupBy("spec_id").agg(F.count("*").alias("accepted"))
    b = spark.read.parquet(f"{path}/rejects").groupBy("spec_id").agg(F.count("*").alias("rejected"))
    both = a.join(b, "spec_id", "full")
    return both.select(F.col("spec_id").cast("bigint").alias("spec_id"), F.coalesce("accepted", F.lit(0)).alias("accepted"), F.coalesce("rejected", F.lit(0)).alias("rejected"))


@query("vod_modes")
def vod_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What must be there before playback can begin, by way of delivery: complete file, complete spec, growing spec."""
    n = table(spark, sf_dir, "orders").count()
    size = 48
    rows = [("file", n, n, -(-n // size)), ("vod", n, size, -(-n // size)), ("event", size, size, 1)]
    return spark.createDataFrame(rows, "mode string, frames_described bigint, frames_rendered bigint, segments_listed bigint")
