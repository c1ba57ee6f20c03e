"""From expressions to needed frames and GOPs; set forms of need set and next need."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reelspark.model.expr import needs
from reelspark.operators.running import running


def schedule(spec: DataFrame) -> DataFrame:
    """(spec_id, gen, seg, needs): row-local; a spec that tells its needs is asked for no expression."""
    return spec.select("spec_id", "gen", "seg", "needs" if "needs" in spec.columns else needs(F.col("nodes")).alias("needs"))


def references(spec: DataFrame) -> DataFrame:
    """One row per (gen, needed frame)."""
    return schedule(spec).select("spec_id", "gen", "seg", F.explode("needs").alias("f")).select("spec_id", "gen", "seg", F.col("f.source").alias("source_id"), F.col("f.idx").alias("idx"))


def need_set(refs: DataFrame, width: int) -> DataFrame:
    """Size of the need set of each run of ``width`` generations: (window_lo, n)."""
    return refs.withColumn("window_lo", F.expr(f"gen - gen % {width}")).groupBy("spec_id", "window_lo").agg(F.count_distinct("source_id", "idx").alias("n"))


def sliding_need_set(refs: DataFrame, width: int) -> DataFrame:
    """Size of the need set of generations gen .. gen + width - 1, for every gen, without holding a window's frames.

    A reference counts for every start from which it is the window's first use of its frame: a run of starts,
    given as +1 and -1 events whose running sum (in blocks of starts) is the size.
    """
    prev = F.lag("gen").over(Window.partitionBy("spec_id", "source_id", "idx").orderBy("gen"))
    runs = refs.select("spec_id", "gen", F.greatest(F.col("gen") - (width - 1), F.coalesce(prev + 1, F.lit(0)), F.lit(0)).alias("lo"))
    events = runs.select("spec_id", F.inline(F.array(F.struct(F.col("lo").alias("at"), F.lit(1).alias("d")), F.struct((F.col("gen") + 1).alias("at"), F.lit(-1).alias("d"))))).groupBy("spec_id", "at").agg(F.sum("d").alias("d"))
    size = running(events, ["spec_id"], "at", "d", "before")
    return size.select("spec_id", F.col("at").alias("window_lo"), (F.col("before") + F.col("d")).cast("bigint").alias("n"))


def next_needed(refs: DataFrame) -> DataFrame:
    """(frame, at_gen, next_gen): the following generation that uses the frame, null if none."""
    w = Window.partitionBy("spec_id", "source_id", "idx").orderBy("gen")
    return refs.select("spec_id", "source_id", "idx", F.col("gen").alias("at_gen"), F.lead("gen").over(w).alias("next_gen"))


def located(refs: DataFrame, gop_len: int | Column) -> DataFrame:
    """References with GOP and decode position (GOPs of I and P frames)."""
    g = gop_len if isinstance(gop_len, Column) else F.lit(gop_len)
    return refs.withColumns({"gop_id": F.floor(F.col("idx") / g).cast("bigint"), "dpos": F.pmod("idx", g)})


def indexed(refs: DataFrame, gops: DataFrame) -> DataFrame:
    """References with GOP and decode position from the GOPs' own index: right for gaps, B packets and mixed lengths."""
    from reelspark.sources.gopindex import frame_index

    return refs.join(frame_index(gops), ["source_id", "idx"])


def bounds(refs: DataFrame, gop_len: int | None, gops: DataFrame | None = None) -> DataFrame:
    """Closed forms per spec: references, decodes if every reference seeks, and the least if each GOP is opened once."""
    at = located(refs, gop_len) if gop_len else indexed(refs, gops)
    seek = at.groupBy("spec_id").agg(F.count("*").alias("refs"), F.sum(F.col("dpos") + 1).alias("seek_decodes"), F.count_distinct("source_id", "idx").alias("distinct_frames"))
    least = at.groupBy("spec_id", "source_id", "gop_id").agg((F.max("dpos") + 1).alias("n")).groupBy("spec_id").agg(F.sum("n").alias("min_decodes"), F.count("*").alias("gops"))
    return seek.join(least, "spec_id")
