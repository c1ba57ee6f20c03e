"""Playlists, segment requests, growing specs, caches."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.engine import exec as engine
from reelspark.operators.running import running
from reelspark.registry import query
from reelspark.session import table
from reelspark.sources.derive import GOP_LEN
from reelspark.vod import segments as vod
from reelspark.workloads.clips import pixels_sql, segment_inputs, task_sources

_SPECS = "SELECT 'coll/' || (o_custkey % 100) AS spec_id, count(*) AS n_frames, 60 AS s, 30000 AS num, 1001 AS den FROM orders GROUP BY 1 UNION ALL SELECT 'main', count(*), 48, 24, 1 FROM orders"
_SEGS = f"WITH sp AS ({_SPECS}), seg AS (SELECT spec_id, CAST(k AS BIGINT) AS seg, CAST(k * s AS BIGINT) AS first_gen, CAST(least(s, n_frames - k * s) AS BIGINT) AS n, CAST(least(s, n_frames - k * s) * 1000 * den // num AS BIGINT) AS millis FROM (SELECT *, unnest(range((n_frames - 1) // s + 1)) AS k FROM sp))"
_LINE = "'#EXTINF:' || (millis // 1000) || '.' || lpad(CAST(millis % 1000 AS VARCHAR), 3, '0') || ',' || chr(10) || spec_id || '/' || seg || '.seg'"


def specs(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    coll = o.groupBy(F.concat(F.lit("coll/"), F.pmod("o_custkey", F.lit(100)).cast("string")).alias("spec_id")).agg(F.count("*").alias("n_frames")).select("spec_id", "n_frames", F.lit(30000).alias("fps_num"), F.lit(1001).alias("fps_den"))
    return coll.unionByName(o.agg(F.count("*").alias("n_frames")).select(F.lit("main").alias("spec_id"), "n_frames", F.lit(24).alias("fps_num"), F.lit(1).alias("fps_den")))


@query("segments", _SEGS + " SELECT spec_id, seg, first_gen, n, millis FROM seg")
def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vod.segment_table(specs(spark, sf_dir))


def _text_sql(kind: str, rows: str = "seg") -> str:
    head = "'#EXTM3U' || chr(10) || '#EXT-X-VERSION:3' || chr(10) || '#EXT-X-TARGETDURATION:2' || chr(10) || '#EXT-X-MEDIA-SEQUENCE:' || min(seg) || chr(10)"
    head += "" if kind == "LIVE" else f" || '#EXT-X-PLAYLIST-TYPE:{kind}' || chr(10)"
    return f" SELECT spec_id, {head} || string_agg({_LINE}, chr(10) ORDER BY seg) || chr(10) || '#EXT-X-ENDLIST' || chr(10) AS text FROM {rows} GROUP BY spec_id"


@query("manifest_vod", _SEGS + _text_sql("VOD"))
def manifest_vod(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vod.playlist(vod.manifest_rows(segments(spark, sf_dir)), "VOD")


@query("manifest_live", _SEGS + ", l AS (SELECT * FROM seg QUALIFY row_number() OVER (PARTITION BY spec_id ORDER BY seg DESC) <= 3)" + _text_sql("LIVE", "l"))
def manifest_live(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sliding look-back of three segments, for contrast: earlier ones are gone."""
    return vod.playlist(vod.manifest_rows(vod.live_rows(segments(spark, sf_dir), 3)), "LIVE")


@query("manifest_mpd", _SEGS + " SELECT spec_id, '<MPD type=\"static\"><SegmentTemplate timescale=\"1000\" media=\"' || spec_id || '/$Number$.seg\"><SegmentTimeline>' || string_agg('<S d=\"' || millis || '\"/>', '' ORDER BY seg) || '</SegmentTimeline></SegmentTemplate></MPD>' AS text FROM seg GROUP BY spec_id")
def manifest_mpd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vod.mpd(vod.manifest_rows(segments(spark, sf_dir)))


@query("player_embed", f"WITH sp AS ({_SPECS}) SELECT spec_id, '<video controls preload=\"metadata\"><source src=\"/' || spec_id || '/playlist.m3u8\" type=\"application/vnd.apple.mpegurl\"></video>' AS html FROM sp")
def player_embed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return specs(spark, sf_dir).select("spec_id", vod.embed(F.col("spec_id")).alias("html"))


# -- growing specs: events as the push log (user = spec, k + 1 frames a push, 30 frames per second) ---------------------

LOG_SQL = "log AS (SELECT user_id, event_id, CAST(json_extract(props, '$.k') AS BIGINT) + 1 AS frames, epoch_us(ts) AS us FROM events)"


def push_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("bigint")
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("spec_id"), F.col("event_id").alias("ord"), (k + 1).alias("frames"), F.expr("unix_micros(cast(ts as timestamp))").alias("us"))


@query("push_frames", f"WITH {LOG_SQL} SELECT user_id AS spec_id, CAST(sum(frames) AS BIGINT) AS frames, CAST(sum(frames) // 60 AS BIGINT) AS listed_open, CAST((sum(frames) + 59) // 60 AS BIGINT) AS listed_closed FROM log GROUP BY 1")
def push_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = push_log(spark, sf_dir).groupBy("spec_id").agg(F.sum("frames").alias("frames"))
    return g.select("spec_id", "frames", F.expr("frames div 60").alias("listed_open"), F.expr("(frames + 59) div 60").alias("listed_closed"))


@query("manifest_event", f"WITH {LOG_SQL}, t AS (SELECT *, sum(frames) OVER (PARTITION BY user_id ORDER BY event_id) AS upto, max(event_id) OVER (PARTITION BY user_id) AS last FROM log), r AS (SELECT user_id, event_id, CAST((upto - frames) // 60 AS BIGINT) AS a, CAST(CASE WHEN event_id = last THEN (upto + 59) // 60 ELSE upto // 60 END AS BIGINT) AS b FROM t) SELECT user_id AS spec_id, unnest(range(a, b)) AS seg, event_id AS at_ord FROM r")
def manifest_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For every segment of every growing spec, the push that makes it appear."""
    return vod.event_rows(push_log(spark, sf_dir), 60)


@query("w_incremental", f"WITH {LOG_SQL}, t AS (SELECT *, sum(frames) OVER (PARTITION BY user_id ORDER BY event_id) AS upto FROM log) SELECT user_id AS spec_id, min(event_id) FILTER (upto >= 60) AS first_push, min(us) FILTER (upto >= 60) - min(us) AS wait_us FROM t GROUP BY 1")
def w_incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """When each spec's first segment can play: at the push that brings its 60th frame."""
    t = running(push_log(spark, sf_dir), ["spec_id"], "ord", "frames", "had").withColumn("upto", F.col("had") + F.col("frames"))
    ready = F.col("upto") >= 60
    return t.groupBy("spec_id").agg(F.min(F.when(ready, F.col("ord"))).alias("first_push"), (F.min(F.when(ready, F.col("us"))) - F.min("us")).alias("wait_us"))


@query("poll", f"WITH {LOG_SQL}, t AS (SELECT user_id, us, sum(frames) OVER (PARTITION BY user_id ORDER BY event_id) AS upto FROM log), p AS (SELECT user_id, CAST(1704067200000000 + d * 86400000000 AS BIGINT) AS poll_us FROM (SELECT DISTINCT user_id FROM log), range(1, 31) r(d)) SELECT p.user_id AS spec_id, p.poll_us, CAST(coalesce(t.upto, 0) // 60 AS BIGINT) AS listed FROM p ASOF LEFT JOIN t ON p.user_id = t.user_id AND p.poll_us >= t.us")
def poll(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a client sees that asks for the playlist once a day while scripts push."""
    from reelspark.operators.joins import asof_join

    log = push_log(spark, sf_dir)
    t = running(log, ["spec_id"], "ord", "frames", "had").select("spec_id", "us", (F.col("had") + F.col("frames")).alias("upto"))
    days = F.explode(F.transform(F.sequence(F.lit(1), F.lit(30)), lambda d: F.lit(1704067200000000) + d * F.lit(86400000000)))
    polls = log.select("spec_id").distinct().select("spec_id", days.alias("poll_us"))
    hit = asof_join(polls, t, "poll_us", "us", ["upto"], 7 * 86_400_000_000, ["spec_id"])
    return hit.select("spec_id", "poll_us", F.expr("coalesce(hit.upto, 0) div 60").alias("listed"))


# -- segments on demand -----------------------------------------------------------------------------------


def _segment(spark: SparkSession, sf_dir: str, seg: int) -> DataFrame:
    """One segment: only its expressions are built and only the GOPs it touches are read."""
    spec, gops = segment_inputs(spark, sf_dir, "box_label", seg)
    return engine.digests(engine.segment_local(spec, gops, task_sources(spark, sf_dir), GOP_LEN)).select("gen", "md5")


@query("render_segment", pixels_sql("box_label", "o_orderkey BETWEEN 0 AND 47"))
def render_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _segment(spark, sf_dir, 0)


@query("random_jump", pixels_sql("box_label", "o_orderkey BETWEEN 1056 AND 1103"))
def random_jump(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _segment(spark, sf_dir, 22)


_REQ = "req AS (SELECT event_id, user_id AS spec_id, CAST(json_extract(props, '$.k') AS BIGINT) % 50 AS seg FROM events)"


def requests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.col("user_id").alias("spec_id"), F.pmod(F.get_json_object("props", "$.k").cast("bigint"), F.lit(50)).alias("seg"))


@query("segment_cache", f"WITH {_REQ} SELECT count(*) AS requests, count(*) - count(DISTINCT (spec_id, seg)) AS hits FROM req")
def segment_cache(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A cache without limit: every request but each segment's first is a hit."""
    per = requests(spark, sf_dir).groupBy("spec_id", "seg").agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("requests"), F.sum(F.col("n") - 1).alias("hits"))


@query("segment_cache_lru")
def segment_cache_lru(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits per host of bounded caches, requests spread by the balancer."""

    def run(t: pd.DataFrame) -> pd.DataFrame:
        out = []
        for cap in (8, 64, 512):
            cache: dict = {}
            hits = 0
            for key in t.sort_values("event_id")[["spec_id", "seg"]].itertuples(index=False, name=None):
                if key in cache:
                    hits += 1
                    cache[key] = cache.pop(key)
                else:
                    cache[key] = None
                    if len(cache) > cap:
                        cache.pop(next(iter(cache)))
            out.append((int(t["host"].iloc[0]), cap, len(t), hits))
        return pd.DataFrame(out, columns=["host", "capacity", "requests", "hits"])

    return vod.assign(requests(spark, sf_dir), 8).groupBy("host").applyInPandas(run, "host int, capacity int, requests bigint, hits bigint")


@query("segment_assign")
def segment_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Load of each of eight hosts; all requests for one segment go to one host."""
    a = vod.assign(requests(spark, sf_dir), 8)
    return a.groupBy("host").agg(F.count("*").alias("requests"), F.count_distinct("spec_id", "seg").alias("segments"))


@query("segment_assign_total", f"WITH {_REQ} SELECT count(*) AS requests, count(DISTINCT (spec_id, seg)) AS segments, count(DISTINCT (spec_id, seg)) AS homes FROM req")
def segment_assign_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All requests are assigned, and every segment has one home: pairs of segment and host are as many as segments."""
    a = vod.assign(requests(spark, sf_dir), 8)
    return a.agg(F.count("*").alias("requests"), F.count_distinct("spec_id", "seg").alias("segments"), F.count_distinct("spec_id", "seg", "host").alias("homes"))
