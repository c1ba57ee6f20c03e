"""Segments and playlists: which runs of generations exist, and how a player hears of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reelspark.model.schemas import SEGMENT_SECONDS
from reelspark.operators.running import numbered, running


def frames_per_segment(num: Column, den: Column) -> Column:
    """Two seconds in whole frames: 60 at 30 and at 30000/1001, 48 at 24."""
    return F.greatest(F.lit(1), F.floor((F.lit(SEGMENT_SECONDS) * num + F.floor(den / F.lit(2))) / den)).cast("bigint")


def segment_table(specs: DataFrame) -> DataFrame:
    """(spec_id, n_frames, fps_num, fps_den) -> (spec_id, seg, first_gen, n, millis); the last may be short."""
    s = frames_per_segment(F.col("fps_num"), F.col("fps_den"))
    rows = specs.where("n_frames > 0").withColumn("s", s).withColumn("seg", F.explode(F.sequence(F.lit(0).cast("bigint"), F.expr("(n_frames - 1) div s"))))
    n = F.least(F.col("s"), F.col("n_frames") - F.col("seg") * F.col("s"))
    return rows.select("spec_id", "seg", (F.col("seg") * F.col("s")).alias("first_gen"), n.alias("n"), F.floor(n * 1000 * F.col("fps_den") / F.col("fps_num")).cast("bigint").alias("millis"))


def uri(spec: Column, seg: Column, ext: str = "seg") -> Column:
    return F.concat(spec, F.lit("/"), seg.cast("string"), F.lit(f".{ext}"))


def manifest_rows(segments: DataFrame, ended: Column | bool = True) -> DataFrame:
    """(spec_id, seq, uri, millis, ended)."""
    return segments.select("spec_id", F.col("seg").alias("seq"), uri(F.col("spec_id"), F.col("seg")).alias("uri"), "millis", (ended if isinstance(ended, Column) else F.lit(ended)).alias("ended"))


def duration(millis: Column) -> Column:
    return F.concat(F.floor(millis / 1000).cast("string"), F.lit("."), F.lpad(F.pmod(millis, F.lit(1000)).cast("string"), 3, "0"))


def playlist(rows: DataFrame, kind: str = "VOD") -> DataFrame:
    """One text per spec. An event playlist without its end is growing; a player asks for it again."""
    lines = F.array_sort(F.collect_list(F.struct("seq", F.concat(F.lit("#EXTINF:"), duration(F.col("millis")), F.lit(",\n"), F.col("uri")).alias("line"))))
    g = rows.groupBy("spec_id").agg(lines.alias("l"), F.bool_or("ended").alias("ended"), F.min("seq").alias("first"))
    head = F.concat(F.lit(f"#EXTM3U\n#EXT-X-VERSION:3\n#EXT-X-TARGETDURATION:{SEGMENT_SECONDS}\n#EXT-X-MEDIA-SEQUENCE:"), F.col("first").cast("string"), F.lit("\n" if kind == "LIVE" else f"\n#EXT-X-PLAYLIST-TYPE:{kind}\n"))
    return g.select("spec_id", F.concat(head, F.array_join(F.col("l.line"), "\n"), F.when(F.col("ended"), F.lit("\n#EXT-X-ENDLIST\n")).otherwise(F.lit("\n"))).alias("text"))


def mpd(rows: DataFrame) -> DataFrame:
    """The XML flavour of the same list."""
    items = F.array_sort(F.collect_list(F.struct("seq", F.concat(F.lit('<S d="'), F.col("millis").cast("string"), F.lit('"/>')).alias("s"))))
    g = rows.groupBy("spec_id").agg(items.alias("l"), F.bool_or("ended").alias("ended"))
    return g.select("spec_id", F.concat(F.lit('<MPD type="'), F.when(F.col("ended"), "static").otherwise("dynamic"), F.lit('"><SegmentTemplate timescale="1000" media="'), F.col("spec_id"), F.lit('/$Number$.seg"><SegmentTimeline>'), F.array_join(F.col("l.s"), ""), F.lit("</SegmentTimeline></SegmentTemplate></MPD>")).alias("text"))


def prefix(pushed: DataFrame, seg_frames: int) -> DataFrame:
    """Pushed generations (spec_id, gen) -> (spec_id, listed): whole segments of the longest run from 0, repeats ignored.

    The n-th distinct generation is in the run if it equals n - 1.
    """
    g = numbered(pushed.select("spec_id", "gen").distinct(), ["spec_id"], "gen", "r")
    return g.groupBy("spec_id").agg(F.expr(f"count_if(gen = r) div {seg_frames}").alias("listed"), F.count_if(F.col("gen") == F.col("r")).alias("prefix"))


def event_rows(log: DataFrame, seg_frames: int, close_last: bool = True) -> DataFrame:
    """A push log (spec_id, ord, frames[, closed]) -> segments with the push that completes each.

    Columns: spec_id, seg, at_ord, ended. Frames of the last, short segment appear once the spec is closed.
    """
    t = running(log, ["spec_id"], "ord", "frames", "had", whole={"last": "last"}).withColumn("upto", F.col("had") + F.col("frames"))
    before = F.expr(f"(upto - frames) div {seg_frames}")
    closing = F.lit(close_last) & (F.col("ord") == F.col("last"))
    now = F.when(closing, F.expr(f"(upto + {seg_frames - 1}) div {seg_frames}")).otherwise(F.expr(f"upto div {seg_frames}"))
    return t.where(now > before).select("spec_id", F.explode(F.sequence(before, now - 1)).alias("seg"), F.col("ord").alias("at_ord"))


def live_rows(segments: DataFrame, lookback: int) -> DataFrame:
    """The last ``lookback`` segments of each spec: what a sliding window keeps."""
    w = Window.partitionBy("spec_id").orderBy(F.desc("seg"))
    return segments.withColumn("k", F.row_number().over(w)).where(F.col("k") <= lookback).drop("k")


def embed(spec: Column) -> Column:
    """HTML for a notebook or a page: a player pointed at the playlist."""
    return F.concat(F.lit('<video controls preload="metadata"><source src="/'), spec, F.lit('/playlist.m3u8" type="application/vnd.apple.mpegurl"></video>'))


def assign(requests: DataFrame, hosts: int) -> DataFrame:
    """Requests spread over render hosts by hash of (spec, segment), so that a host meets its segments again."""
    return requests.withColumn("host", F.pmod(F.xxhash64("spec_id", "seg"), F.lit(hosts)).cast("int"))
