"""Window operators over clips, detections and telemetry."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reelspark.registry import query
from reelspark.session import table

_C = "SELECT o_orderkey AS i, o_custkey % 100 AS c FROM orders"
_W = "(PARTITION BY c ORDER BY i)"


def _clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("i"), F.pmod("o_custkey", F.lit(100)).alias("c"))


def _w():
    return Window.partitionBy("c").orderBy("i")


for _name, _sql, _f in (
    ("win_row_number", "CAST(row_number() OVER {w} AS BIGINT)", lambda: F.row_number().over(_w()).cast("bigint")),
    ("win_rank", "CAST(rank() OVER (PARTITION BY c ORDER BY i // 500) AS BIGINT)", lambda: F.rank().over(Window.partitionBy("c").orderBy(F.expr("i div 500"))).cast("bigint")),
    ("win_dense_rank", "CAST(dense_rank() OVER (PARTITION BY c ORDER BY i // 500) AS BIGINT)", lambda: F.dense_rank().over(Window.partitionBy("c").orderBy(F.expr("i div 500"))).cast("bigint")),
    ("win_ntile", "CAST(ntile(4) OVER {w} AS BIGINT)", lambda: F.ntile(4).over(_w()).cast("bigint")),
    ("win_percent_rank", "round(percent_rank() OVER {w}, 9)", lambda: F.round(F.percent_rank().over(_w()), 9)),
    ("win_cume_dist", "round(cume_dist() OVER {w}, 9)", lambda: F.round(F.cume_dist().over(_w()), 9)),
    ("win_lag_lead", "i - lag(i, 1, -1) OVER {w} + coalesce(lead(i) OVER {w}, 0)", lambda: F.col("i") - F.lag("i", 1, -1).over(_w()) + F.coalesce(F.lead("i").over(_w()), F.lit(0))),
    ("win_first_last_nth", "first_value(i) OVER {f} + last_value(i) OVER {f} * 3 + nth_value(i, 2) OVER {f} * 7", lambda: F.first("i").over(_all()) + F.last("i").over(_all()) * 3 + F.nth_value("i", 2).over(_all()) * 7),
    ("win_rows", "CAST(sum(i) OVER (PARTITION BY c ORDER BY i ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS BIGINT)", lambda: F.sum("i").over(_w().rowsBetween(-4, 0))),
    ("win_range", "count(*) OVER (PARTITION BY c ORDER BY i RANGE BETWEEN CURRENT ROW AND 800 FOLLOWING)", lambda: F.count("*").over(_w().rangeBetween(0, 800))),
    ("win_running", "CAST(sum(i % 7) OVER {w} AS BIGINT)", lambda: F.sum(F.pmod("i", F.lit(7))).over(_w())),
):
    query(_name, f"WITH t AS ({_C}) SELECT i, " + _sql.format(w=_W, f="(PARTITION BY c ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)") + " AS v FROM t")(lambda spark, sf_dir, f=_f: _clips(spark, sf_dir).select("i", f().alias("v")))


def _all():
    return _w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)


@query("win_gaps_islands", "WITH t AS (SELECT DISTINCT l_orderkey AS i FROM lineitem WHERE l_returnflag = 'A'), g AS (SELECT i, i - row_number() OVER (ORDER BY i) AS k FROM t) SELECT min(i) AS first, max(i) AS last, count(*) AS n FROM g GROUP BY k")
def win_gaps_islands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contiguous runs of frames with an object of class A.

    Runs are found inside blocks of frames first, then those that touch at a block's edge are joined, so
    no window holds more than one row per block of the whole clip.
    """
    t = table(spark, sf_dir, "lineitem").where("l_returnflag = 'A'").select(F.col("l_orderkey").alias("i")).distinct().withColumn("block", F.expr("i div 4096"))
    g = t.withColumn("k", F.col("i") - F.row_number().over(Window.partitionBy("block").orderBy("i")))
    runs = g.groupBy("block", "k").agg(F.min("i").alias("first"), F.max("i").alias("last"), F.count("*").alias("n"))
    inner = runs.where("first % 4096 <> 0 AND last % 4096 <> 4095").select("first", "last", "n")
    edge = runs.where("first % 4096 = 0 OR last % 4096 = 4095")
    w = Window.orderBy("first")
    joined = edge.withColumn("new", F.coalesce((F.lag("last").over(w) + 1 != F.col("first")).cast("int"), F.lit(1))).withColumn("run", F.sum("new").over(w))
    return inner.unionByName(joined.groupBy("run").agg(F.min("first").alias("first"), F.max("last").alias("last"), F.sum("n").alias("n")).select("first", "last", "n"))


@query("win_next_needed", "SELECT l_partkey % 500 AS frame, l_orderkey AS at_gen, lead(l_orderkey) OVER (PARTITION BY l_partkey % 500 ORDER BY l_orderkey) AS next_gen FROM (SELECT DISTINCT l_partkey, l_orderkey FROM (SELECT l_partkey % 500 AS l_partkey, l_orderkey FROM lineitem))")
def win_next_needed(spark: SparkSession, sf_dir: str) -> DataFrame:
    refs = table(spark, sf_dir, "lineitem").select(F.pmod("l_partkey", F.lit(500)).alias("frame"), F.col("l_orderkey").alias("at_gen")).distinct()
    return refs.withColumn("next_gen", F.lead("at_gen").over(Window.partitionBy("frame").orderBy("at_gen")))
