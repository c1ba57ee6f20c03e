"""Joins of frames with their side data, with the strategies that scale and the cases where they matter."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reelspark.operators.relational import WITH_DETS
from reelspark.registry import query
from reelspark.session import table
from reelspark.sources.derive import detections

_BY_BRAND = "SELECT p_brand AS brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1"


def _by_brand(spark: SparkSession, sf_dir: str, hint: str) -> DataFrame:
    li, p = table(spark, sf_dir, "lineitem").select("l_partkey"), table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return li.join(p.hint(hint), F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("p_brand").alias("brand")).agg(F.count("*").alias("n"))


for _name, _hint in (("join_inner_hash", "shuffle_hash"), ("join_smj", "merge")):
    query(_name, _BY_BRAND)(lambda spark, sf_dir, hint=_hint: _by_brand(spark, sf_dir, hint))

#: Rows below which a side may be broadcast; its size is counted first.
BROADCAST_ROWS = 100_000


def sized_broadcast(df: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint only if the side has at most ``most`` rows (counting stops there); else the optimiser chooses."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


@query("join_broadcast", _BY_BRAND)
def join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = sized_broadcast(table(spark, sf_dir, "part").select("p_partkey", "p_brand"))
    return table(spark, sf_dir, "lineitem").join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("p_brand").alias("brand")).agg(F.count("*").alias("n"))


def box_area(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    return F.greatest(F.lit(0), x2 - x1 + 1) * F.greatest(F.lit(0), y2 - y1 + 1)


@query("join_bnl", WITH_DETS + "SELECT a.frame, CAST(a.ord AS BIGINT) AS a, CAST(b.ord AS BIGINT) AS b, CAST((least(a.x2, b.x2) - greatest(a.x1, b.x1) + 1) * (least(a.y2, b.y2) - greatest(a.y1, b.y1) + 1) AS BIGINT) AS overlap FROM dets a JOIN dets b ON a.frame = b.frame AND a.ord < b.ord AND least(a.x2, b.x2) >= greatest(a.x1, b.x1) AND least(a.y2, b.y2) >= greatest(a.y1, b.y1)")
def join_bnl(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overlapping boxes inside a frame: the theta part is checked within the frame's own (at most a few dozen) objects."""
    d = detections(spark, sf_dir).select("frame", "ord", "x1", "y1", "x2", "y2")
    a, b = d.alias("a"), d.alias("b")
    x, y = F.least("a.x2", "b.x2") - F.greatest("a.x1", "b.x1") + 1, F.least("a.y2", "b.y2") - F.greatest("a.y1", "b.y1") + 1
    on = (F.col("a.frame") == F.col("b.frame")) & (F.col("a.ord") < F.col("b.ord")) & (x > 0) & (y > 0)
    return a.join(b, on).select(F.col("a.frame").alias("frame"), F.col("a.ord").cast("bigint").alias("a"), F.col("b.ord").cast("bigint").alias("b"), (x * y).cast("bigint").alias("overlap"))


for _name, _how, _sql in (("join_left", "left", "LEFT"), ("join_right", "right", "RIGHT"), ("join_full", "full", "FULL")):
    query(_name, f"SELECT coalesce(d.doc_id, l.doc_id) AS id, d.source, l.quality FROM (SELECT doc_id, source FROM documents WHERE lang = 'en') d {_sql} JOIN labels l ON d.doc_id = l.doc_id")(
        lambda spark, sf_dir, how=_how: table(spark, sf_dir, "documents").where("lang = 'en'").select("doc_id", "source").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", how).withColumnRenamed("doc_id", "id")
    )
for _name, _how, _sql in (("join_semi", "left_semi", "IN"), ("join_anti", "left_anti", "NOT IN")):
    query(_name, f"SELECT o_orderkey AS frame FROM orders WHERE o_orderkey {_sql} (SELECT l_orderkey FROM lineitem)")(
        lambda spark, sf_dir, how=_how: table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("frame")).join(table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("frame")), "frame", how)
    )


def range_join(left: DataFrame, right: DataFrame, lo: str, hi: str, start: str, end: str, width: int) -> DataFrame:
    """Pairs whose closed intervals overlap: both sides go to the buckets they touch, meet by equality, and
    each pair counts in the first bucket that both touch. No nested loop; ``width`` should be near the usual length."""
    b = lambda c: F.floor(F.col(c) / F.lit(width)).cast("bigint")
    a = left.withColumn("bucket", F.explode(F.sequence(b(lo), b(hi))))
    z = right.withColumn("bucket", F.explode(F.sequence(b(start), b(end))))
    meet = (F.col(lo) <= F.col(end)) & (F.col(start) <= F.col(hi)) & (F.col("bucket") == F.greatest(b(lo), b(start)))
    return a.join(z, "bucket").where(meet).drop("bucket")


@query("join_range", "WITH e AS (SELECT event_id, epoch_us(ts) // 1000000 AS s, epoch_us(ts) // 1000000 + CAST(floor(value) AS BIGINT) AS t FROM events), c AS (SELECT o_orderkey AS clip, 1704067200 + o_orderkey * 977 AS a, 1704067200 + o_orderkey * 977 + 120 AS b FROM orders) SELECT clip, event_id FROM c JOIN e ON e.s <= c.b AND c.a <= e.t")
def join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = F.expr("unix_micros(cast(ts as timestamp)) div 1000000")
    e = table(spark, sf_dir, "events").select("event_id", s.alias("s"), (s + F.floor("value").cast("bigint")).alias("t"))
    a = F.lit(1704067200) + F.col("o_orderkey") * 977
    c = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("clip"), a.alias("a"), (a + 120).alias("b"))
    return range_join(c, e, "a", "b", "s", "t", 240).select("clip", "event_id")


def asof_join(left: DataFrame, right: DataFrame, at: str, time: str, value: list[str], bucket: int, by: list[str] | None = None) -> DataFrame:
    """Each left row with the latest right row at or before it (ties: the larger value struct).

    Rows are cut into time buckets, so a window never spans the whole of time; what a bucket without
    an earlier row of its own needs is the last right row of the buckets before, from a window over one row per bucket.
    """
    by = by or []
    cut = lambda c: F.floor(F.col(c) / F.lit(bucket)).cast("bigint")
    pack = F.struct(F.col(time).alias("t"), *value)
    r = right.select(*by, F.col(time).alias("at"), pack.alias("v"), cut(time).alias("bucket"), F.lit(0).alias("kind"), F.lit(None).cast(dict_type(left)).alias("row"))
    keep = F.struct(*[F.col(c) for c in left.columns])
    q = left.select(*by, F.col(at).alias("at"), F.lit(None).cast(r.schema["v"].dataType).alias("v"), cut(at).alias("bucket"), F.lit(1).alias("kind"), keep.alias("row"))
    both = r.unionByName(q)
    w = Window.partitionBy(*by, "bucket").orderBy("at", "kind", "v").rowsBetween(Window.unboundedPreceding, 0)
    inner = both.withColumn("seen", F.last("v", ignorenulls=True).over(w))
    ends = both.groupBy(*by, "bucket").agg(F.max("v").alias("top"))
    carry = F.last("top", ignorenulls=True).over(Window.partitionBy(*by).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))
    ends = ends.select(*by, "bucket", carry.alias("carried"))
    out = inner.where("kind = 1").join(ends, [*by, "bucket"])
    return out.select("row.*", F.coalesce("seen", "carried").alias("hit"))


def dict_type(df: DataFrame):
    from pyspark.sql.types import StructType

    return StructType(df.schema.fields)


@query("join_asof", "WITH f AS (SELECT o_orderkey AS frame, 1704067200000000 + o_orderkey * 100000000 AS at FROM orders), e AS (SELECT event_id, epoch_us(ts) AS t, value FROM events) SELECT f.frame, e.event_id, e.value FROM f ASOF LEFT JOIN e ON f.at >= e.t")
def join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("frame"), (F.lit(1704067200000000) + F.col("o_orderkey") * 100000000).alias("at"))
    e = table(spark, sf_dir, "events").select("event_id", F.expr("unix_micros(cast(ts as timestamp))").alias("t"), "value")
    return asof_join(f, e, "at", "t", ["event_id", "value"], 86_400_000_000).select("frame", "hit.event_id", "hit.value")


_TOP2 = WITH_DETS + "SELECT frame, CAST(ord AS BIGINT) AS ord, k FROM (SELECT frame, ord, CAST(row_number() OVER (PARTITION BY frame ORDER BY conf DESC, ord) AS BIGINT) AS k FROM dets) WHERE k <= 2"


@query("join_lateral", _TOP2)
def join_lateral(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A label budget of two per frame; the rank window replaces a lateral sub-query per frame."""
    w = Window.partitionBy("frame").orderBy(F.desc("conf"), "ord")
    return detections(spark, sf_dir).withColumn("k", F.row_number().over(w).cast("bigint")).where("k <= 2").select("frame", F.col("ord").cast("bigint").alias("ord"), "k")


query("topk_per_group", _TOP2)(join_lateral)


@query("join_cross", "SELECT r_name AS region, k.pool, k.win FROM region, (SELECT * FROM (VALUES (10, 8), (30, 24), (100, 80)) AS t(pool, win)) k")
def join_cross(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A grid of settings: 5 regions by 3 settings, both of fixed size, written as rows of an array."""
    grid = F.inline(F.array(*[F.struct(F.lit(p).alias("pool"), F.lit(w).alias("win")) for p, w in ((10, 8), (30, 24), (100, 80))]))
    return table(spark, sf_dir, "region").select(F.col("r_name").alias("region"), grid)


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int, spread: Column) -> DataFrame:
    """Equi-join for hot keys: the large side's rows of a key go to ``salts`` partitions, the small side is copied to each."""
    a = large.withColumn("salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    b = small.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "salt"]).drop("salt")


@query("join_salted", "SELECT l_returnflag AS cls, p.bgr, count(*) AS n FROM lineitem JOIN (VALUES ('A', '0,0,255'), ('N', '0,255,0'), ('R', '255,0,0')) p(cls, bgr) ON l_returnflag = p.cls GROUP BY ALL")
def join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("cls"), "l_orderkey")
    palette = spark.createDataFrame([("A", "0,0,255"), ("N", "0,255,0"), ("R", "255,0,0")], "cls string, bgr string")
    return salted_join(li, palette, "cls", 8, F.col("l_orderkey")).groupBy("cls", "bgr").agg(F.count("*").alias("n"))
