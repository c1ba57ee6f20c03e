"""Access patterns over frames."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reelspark.engine.core import EngineConfig, simulate
from reelspark.plans.schedule import bounds
from reelspark.registry import query
from reelspark.session import table


def shuffled(frames: DataFrame, seed: int = 7, buckets: int = 256) -> DataFrame:
    """(gen, idx): a permutation by md5 of seed and index, reproducible in SQL.

    The global position is the count of smaller buckets plus the rank inside the own bucket (the first
    hash byte), so no window holds the whole clip.
    """
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col("idx").cast("string")))
    rows = frames.withColumn("h", h).withColumn("b", F.substring("h", 1, 2))
    rank = F.row_number().over(Window.partitionBy("b").orderBy("h", "idx"))
    sizes = rows.groupBy("b").agg(F.count("*").alias("n"))
    starts = sizes.select("b", (F.sum("n").over(Window.orderBy("b")) - F.col("n")).alias("start"))
    return rows.withColumn("r", rank).join(F.broadcast(starts), "b").withColumn("gen", (F.col("start") + F.col("r") - 1).cast("bigint")).drop("h", "b", "r", "start")


# -- registered patterns: closed forms for every pattern, counters of the engine for the dense ones --------------

GOPS = (30, 60, 250)
_LONG = 8_192_000  # frames of the virtual clip: 1,000 frames at the widest stride


def pattern(clip: DataFrame, name: str) -> DataFrame:
    """(gen, idx) of an access pattern over (idx)."""
    if name == "every":
        return clip.select(F.col("idx").alias("gen"), "idx")
    if name == "reverse":
        last = clip.agg(F.max("idx").alias("last"))
        return clip.join(F.broadcast(last), F.lit(True)).select((F.col("last") - F.col("idx")).alias("gen"), "idx")
    return shuffled(clip).select("gen", "idx")


def _refs(p: DataFrame, spec: str) -> DataFrame:
    return p.select(F.lit(spec).alias("spec_id"), "gen", F.lit("clip").alias("source_id"), "idx")


_BOUNDS = "SELECT spec_id AS pattern, CAST({g} AS BIGINT) AS gop_len, count(*) AS refs, CAST(sum(idx % {g} + 1) AS BIGINT) AS seek_decodes, CAST((SELECT sum(m) FROM (SELECT max(idx % {g}) + 1 AS m FROM r x WHERE x.spec_id = r.spec_id GROUP BY idx // {g})) AS BIGINT) AS min_decodes FROM r GROUP BY 1"


def _bounds(refs: DataFrame) -> DataFrame:
    out = None
    for g in GOPS:
        one = bounds(refs, g).select(F.col("spec_id").alias("pattern"), F.lit(g).cast("bigint").alias("gop_len"), "refs", "seek_decodes", "min_decodes")
        out = one if out is None else out.unionByName(one)
    return out


def _bounds_sql(refs: str) -> str:
    return f"WITH r AS ({refs}) " + " UNION ALL ".join(_BOUNDS.format(g=g) for g in GOPS)


@query("base_seek", _bounds_sql("SELECT 'every' AS spec_id, vec_id AS idx FROM embeddings UNION ALL SELECT 'reverse', vec_id FROM embeddings UNION ALL SELECT 'shuffled', vec_id FROM embeddings"))
def base_seek(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dense patterns: decodes if every reference seeks, and the least possible."""
    clip = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("idx"))
    out = None
    for name in ("every", "reverse", "shuffled"):
        one = _refs(pattern(clip, name), name)
        out = one if out is None else out.unionByName(one)
    return _bounds(out)


@query("w_sparse_bounds", _bounds_sql("SELECT 'stride ' || s AS spec_id, CAST(k * s AS BIGINT) AS idx FROM (SELECT CAST(2 ** e AS BIGINT) AS s FROM range(14) t(e)), (SELECT o_orderkey AS k FROM orders ORDER BY o_orderkey LIMIT 1000)"))
def w_sparse_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strides 1 to 8192 over the main clip, repeated to 8,192,000 frames: a generation for each of its first 1,000 frames; index only."""
    gens = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("gen")).orderBy("gen").limit(1000)
    rows = gens.select("gen", F.explode(F.array(*[F.lit(1 << e).cast("bigint") for e in range(14)])).alias("s"))
    return _bounds(rows.select(F.concat(F.lit("stride "), F.col("s").cast("string")).alias("spec_id"), F.col("gen").cast("bigint").alias("gen"), F.lit("clip").alias("source_id"), (F.col("gen") * F.col("s")).alias("idx")))


def simulated(spark: SparkSession, cases: list[dict], schedules: dict[str, list[list[int]]]) -> DataFrame:
    """Counters of the scheduler for a list of settings, one task each; schedules are a workload's own few
    hundred generations."""
    from pyspark.sql.types import StructType

    schema = "pattern string, gop_len int, pool int, win int, decoders int, filters int, evict string, frames_decoded bigint, gop_opens bigint, abandons bigint, evictions bigint, drops bigint, peak_pool bigint, ticks bigint"
    names = StructType.fromDDL(schema).names

    def run(it):
        import pandas as pd

        for batch in it:
            out = []
            for c in batch.to_dict("records"):
                cfg = EngineConfig(pool=c["pool"], window=c["win"], decoders=c["decoders"], filters=c["filters"], evict=c["evict"])
                out.append({**c, **simulate(schedules[c["pattern"]], c["gop_len"], None, cfg)})
            yield pd.DataFrame(out)[names]

    keys = "pattern string, gop_len int, pool int, win int, decoders int, filters int, evict string"
    rows = [(c["pattern"], c["gop_len"], c["pool"], c["win"], c["decoders"], c.get("filters", 4), c.get("evict", "next_needed")) for c in cases]
    return spark.createDataFrame(rows, keys).repartition(min(len(rows), 64)).mapInPandas(run, schema)


def clip_frames(spark: SparkSession, sf_dir: str, n: int) -> list[int]:
    """The first n frames of the main clip, by their keys: what a study of n generations runs over."""
    return [r["o_orderkey"] for r in table(spark, sf_dir, "orders").select("o_orderkey").orderBy("o_orderkey").limit(n).collect()]


def dense(spark: SparkSession, sf_dir: str, n: int = 500) -> dict[str, list[list[int]]]:
    return dense_schedules(n, clip_frames(spark, sf_dir, n))


def dense_schedules(n: int = 500, frames: list[int] | None = None) -> dict[str, list[list[int]]]:
    import hashlib

    every = [[i] for i in (range(n) if frames is None else frames)]
    return {"every": every, "reverse": every[::-1], "shuffled": sorted(every, key=lambda x: hashlib.md5(f"7:{x[0]}".encode()).hexdigest())}


@query("w_dense")
def w_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    """500 frames: pattern by pool size. Frames decoded fall as the pool grows; reverse meets the least at one GOP."""
    cases = [{"pattern": p, "gop_len": g, "pool": k, "win": max(1, k * 8 // 10), "decoders": 4} for p in ("every", "reverse", "shuffled") for g in (60, 250) for k in (10, 30, 60, 100, 250, 500)]
    return simulated(spark, cases, dense(spark, sf_dir))


@query("w_dense_evict")
def w_dense_evict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Look-ahead eviction against least-recently-used, first-in-first-out and random."""
    cases = [{"pattern": p, "gop_len": 60, "pool": k, "win": max(1, k * 8 // 10), "decoders": 4, "evict": e} for p in ("reverse", "shuffled") for k in (30, 100) for e in ("next_needed", "lru", "fifo", "random")]
    return simulated(spark, cases, dense(spark, sf_dir))


@query("w_reverse")
def w_reverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reversal by decoders, pool and GOP length; a pool of one GOP cures it."""
    cases = [{"pattern": "reverse", "gop_len": g, "pool": k, "win": max(1, k * 8 // 10), "decoders": d, "filters": 8} for g in (30, 60, 250) for k in (16, 32, 64, 100, 256) for d in (1, 2, 4, 8, 16)]
    return simulated(spark, cases, dense(spark, sf_dir))


@query("w_prefetch")
def w_prefetch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Window of active generations at a pool of 100."""
    cases = [{"pattern": p, "gop_len": 60, "pool": 100, "win": w, "decoders": 4} for p in ("every", "reverse", "shuffled") for w in (1, 5, 20, 40, 80, 100)]
    return simulated(spark, cases, dense(spark, sf_dir))


@query("w_sparse")
def w_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strides by decoders, in simulated ticks: wide strides gain in proportion to decoders."""
    strides = {f"stride {2**e}": [[k * 2**e] for k in clip_frames(spark, sf_dir, 1000)] for e in range(14)}
    cases = [{"pattern": p, "gop_len": 60, "pool": 100, "win": 80, "decoders": d, "filters": 16} for p in strides for d in (1, 2, 4, 8, 16)]
    return simulated(spark, cases, strides)


@query("w_threads")
def w_threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tasks by number of decoders and filters, in simulated ticks (not seconds): pool 100, window 80."""
    n, clip = 480, clip_frames(spark, sf_dir, 16_384)
    at = lambda i: clip[i % len(clip)]  # noqa: E731  a clip that is shorter is played again
    tasks = {"box_label": [[at(i)] for i in range(n)], "one_per_second": [[at(i * 24)] for i in range(n // 4)], "keyframes": [[at(i * 60)] for i in range(n // 8)], "side_by_side": [[at(i), at(i + 2000), at(i + 4000), at(i + 6000)] for i in range(n // 2)], "reverse": [[at(i)] for i in range(n)][::-1], "compilation": [[at(c * 1777 + k)] for c in range(8) for k in range(48)]} if clip else {}
    cases = [{"pattern": p, "gop_len": 60, "pool": 100, "win": 80, "decoders": d, "filters": d} for p in tasks for d in (1, 2, 4, 8, 16)]
    out = simulated(spark, cases, tasks)
    w = Window.partitionBy("pattern").orderBy("decoders")
    speed = F.first("ticks").over(w) / F.col("ticks")
    return out.withColumn("speedup", F.round(speed, 3)).withColumn("efficiency", F.round(speed / F.col("decoders"), 3))


@query("w_pool_bytes", "WITH c AS (SELECT 'coll/' || (o_custkey % 100) AS clip, count(*) AS n FROM orders GROUP BY 1) SELECT clip, k AS size, CAST(least(100, n) * w * h * 3 AS BIGINT) AS bgr_bytes, CAST(least(100, n) * w * h * 3 // 2 AS BIGINT) AS native_bytes FROM c, (VALUES ('720p', 1280, 720), ('1080p', 1920, 1080), ('main', 16, 16)) v(k, w, h)")
def w_pool_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of a full pool of 100 frames (all, if a clip has fewer) for every clip of the collection at three sizes, in three-byte and in native pixels."""
    clips = table(spark, sf_dir, "orders").groupBy(F.concat(F.lit("coll/"), F.pmod("o_custkey", F.lit(100)).cast("string")).alias("clip")).agg(F.least(F.lit(100), F.count("*")).alias("n"))
    sizes = F.inline(F.array(*[F.struct(F.lit(k).alias("size"), F.lit(w).cast("bigint").alias("w"), F.lit(h).cast("bigint").alias("h")) for k, w, h in (("720p", 1280, 720), ("1080p", 1920, 1080), ("main", 16, 16))]))
    return clips.select("clip", "n", sizes).select("clip", "size", (F.col("n") * F.col("w") * F.col("h") * 3).alias("bgr_bytes"), F.expr("n * w * h * 3 div 2").alias("native_bytes"))


@query("admission_trace")
def admission_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """States of the generations of one shuffled run: (tick, gen, state)."""
    from reelspark.engine.core import Engine

    rows: list[tuple] = []
    s = dense(spark, sf_dir)["shuffled"]
    Engine(s, lambda f: f // 60, lambda g: list(range(g * 60, g * 60 + 60)), EngineConfig(pool=40, window=32, decoders=3, filters=4), trace=lambda *x: rows.append(x)).run()
    return spark.createDataFrame(rows, "tick bigint, gen bigint, state string")
