"""Annotation tasks by engine and by script, decode plans, and how they compare."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.baseline import script
from reelspark.engine import exec as engine
from reelspark.engine.core import EngineConfig
from reelspark.lift import relational
from reelspark.registry import query
from reelspark.sources import derive, gopindex
from reelspark.sources.derive import GOP_LEN
from reelspark.workloads.clips import SEG, TASKS, frames_sql, pixels_sql, stored_detections, stored_lists, task_gops, task_sources, task_spec


def rendered(spark: SparkSession, sf_dir: str, recipe: str, plan: str = "segment_local", config: EngineConfig = EngineConfig(), conversion: str = "lazy", stored: bool = False) -> DataFrame:
    spec = task_spec(spark, sf_dir, recipe, conversion, needed=True, stored=stored)
    return engine.render(spec, task_gops(spark, sf_dir, recipe), task_sources(spark, sf_dir), GOP_LEN, config, plan)


def _digest(df: DataFrame) -> DataFrame:
    return engine.digests(df).select("gen", "md5")


for _name, _recipe in TASKS.items():
    query(_name, pixels_sql(_recipe))(lambda spark, sf_dir, recipe=_recipe: _digest(rendered(spark, sf_dir, recipe, "gop_exchange" if recipe.startswith("mask") else "segment_local")))


@query("render_full", pixels_sql("box"))
def render_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _digest(rendered(spark, sf_dir, "box", "auto"))


@query("plan_gop_exchange", pixels_sql("box"))
def plan_gop_exchange(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _digest(rendered(spark, sf_dir, "box", "gop_exchange"))


@query("render_eager", pixels_sql("box", eager=True))
def render_eager(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversions at read and at write of every frame, as a script does them."""
    return _digest(rendered(spark, sf_dir, "box", conversion="eager"))


@query("base_script", pixels_sql("box_label", eager=True))
def base_script(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sequential script's frames: it is started for parts of the clip side by side, as a clip of any length is too long for one task."""
    return _digest(script.render(task_gops(spark, sf_dir, "box_label"), derive.detections(spark, sf_dir), "box_label", alone=False))


_EXACT = " UNION ALL ".join(
    f"SELECT '{t}' AS task, '{kind}' AS conversion, '{plan}' AS plan, {n} AS gens, CAST(0 AS BIGINT) AS differ"
    for t in sorted(TASKS.values())
    for kind, plan, n in (("eager", "segment_local", "(SELECT count(*) FROM orders)"), ("eager", "gop_exchange", "(SELECT count(*) FROM orders)"), ("lazy, drawn", "segment_local", "(SELECT count(DISTINCT l_orderkey) FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders))"))
)


@query("m_exact", _EXACT)
def m_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Generations whose bytes differ between engine and script, over all five tasks: none of all generations with conversions at read
    and write, under both plans; and none of those with a draw where conversions are left out if nothing is drawn."""
    hit = stored_lists(spark, sf_dir).where("size(dets) > 0").select("gen", F.lit(4).alias("by"), F.lit(None).cast("string").alias("md5"))
    out = None
    for recipe in sorted(TASKS.values()):
        # what each has for a generation meets in one grouping, whose rows are as many as the generations that any of them has
        both, hashed = hit, lambda df, k: df.select("gen", F.lit(k).alias("by"), F.md5("data").alias("md5"))
        for k, (conversion, plan) in enumerate((("eager", "segment_local"), ("eager", "gop_exchange"), ("lazy", "segment_local"))):
            both = both.unionByName(hashed(rendered(spark, sf_dir, recipe, plan, conversion=conversion, stored=True), k))
        both = both.unionByName(hashed(script.render(task_gops(spark, sf_dir, recipe), stored_detections(spark, sf_dir), recipe, alone=False), 3))
        of = lambda k: F.when(F.col("by") == k, F.col("md5"))
        both = both.groupBy("gen").agg(*[F.max(of(k)).alias(f"x{k}") for k in range(4)], *[F.count(of(k)).alias(f"n{k}") for k in range(4)], F.max(F.when(F.col("by") == 4, True)).alias("drawn"))
        differ = lambda k: F.when(~F.col(f"x{k}").eqNullSafe(F.col("x3")) | (F.col(f"n{k}") != 1) | (F.col("n3") != 1), F.lit(1))
        one = both.agg(F.count("*").alias("n"), F.count(differ(0)).alias("d0"), F.count(differ(1)).alias("d1"), F.count("drawn").alias("m"), F.count(F.when(F.col("drawn"), differ(2))).alias("d2"))
        row = lambda kind, plan, n, d: F.struct(F.lit(recipe).alias("task"), F.lit(kind).alias("conversion"), F.lit(plan).alias("plan"), F.col(n).alias("gens"), F.col(d).alias("differ"))  # noqa: B023, E731
        one = one.select(F.inline(F.array(row("eager", "segment_local", "n", "d0"), row("eager", "gop_exchange", "n", "d1"), row("lazy, drawn", "segment_local", "m", "d2"))))
        out = one if out is None else out.unionByName(one)
    return out


@query("m_lossy_round_trip")
def m_lossy_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Untouched frames: how many differ between eager and lazy conversion, per clip."""
    out = None
    for source, frames, w in (("main", derive.main_frames(spark, sf_dir), 16), ("short", derive.short_frames(spark, sf_dir), 8)):
        sources = spark.createDataFrame([(source, w, w, "yuv420p")], "source_id string, width int, height int, fmt string")
        index = frames.select(F.col("idx").alias("gen"), F.lit(source).alias("source_id"), "idx")
        none = derive.detections(spark, sf_dir).where("false")
        spec = relational.annotate(index, none, "box", source, SEG, conversion="eager")
        eager = engine.gop_exchange(spec, gopindex.encode(frames), sources, GOP_LEN)
        one = eager.select(F.col("gen").alias("idx"), "data").join(frames.hint("merge"), "idx").agg(F.lit(source).alias("source_id"), F.count("*").alias("frames"), F.count_if(F.col("data") != F.col("raw")).alias("differ"))
        out = one if out is None else out.unionByName(one)
    return out


@query("base_prebaked", pixels_sql("box"))
def base_prebaked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The overlay is fixed when the clip is stored: written once as packets, read and decoded for playback."""
    from reelspark.sources.io import shared_folder

    path = shared_folder(spark, "prebaked")
    engine.encoded(rendered(spark, sf_dir, "box"), SEG).write.parquet(path)
    back = spark.read.parquet(path).select(F.lit("baked").alias("source_id"), F.col("seg").alias("gop_id"), F.lit(0).cast("bigint").alias("first_idx"), "n", "packets")
    frames = gopindex.decode(back).select(F.lit("baked").alias("spec_id"), F.col("idx").alias("gen"), F.lit(16).alias("w"), F.lit(16).alias("h"), F.lit("yuv420p").alias("fmt"), F.col("raw").alias("data"))
    return _digest(frames)


@query("f_base", "WITH f AS (" + frames_sql() + ") SELECT i AS frame, md5(string_agg(CAST((3 * i + 7 * x + 11 * y + p) % 256 AS VARCHAR), ',' ORDER BY y, x)) AS md5 FROM f, range(16) tx(x), range(16) ty(y) GROUP BY i")
def f_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Luma of every frame after a round trip through the codec with B packets."""
    from reelspark.functions.udfs import digest

    back = gopindex.decode(gopindex.encode(derive.main_frames(spark, sf_dir), 30, 2))
    md5 = F.udf(lambda r: digest(r[:256]), "string", useArrow=True)
    return back.select(F.col("idx").alias("frame"), md5("raw").alias("md5"))


@query("m_stats")
def m_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Engine counters per segment of the box-and-label task."""
    spec = task_spec(spark, sf_dir, "box_label", needed=True)
    return engine.segment_stats(spec, task_gops(spark, sf_dir, "box_label"), task_sources(spark, sf_dir), GOP_LEN)


@query("cost_choose")
def cost_choose(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates of both decode plans for a sequential and a scattered task."""
    from reelspark.plans import cost
    from reelspark.plans.schedule import references

    out = None
    for recipe in ("box_label", "mask_label"):
        one = cost.choose(references(task_spec(spark, sf_dir, recipe)), GOP_LEN, 384).withColumn("task", F.lit(recipe))
        out = one if out is None else out.unionByName(one)
    return out
