"""Filters, projections, aggregates, sets and order over the side data of clips."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.registry import query
from reelspark.session import table
from reelspark.sources.derive import DETECTIONS_SQL, detections

WITH_DETS = f"WITH dets AS ({DETECTIONS_SQL}) "


@query("proj_box", WITH_DETS + "SELECT frame, CAST(ord AS BIGINT) AS ord, CAST(x1 AS BIGINT) AS x1, CAST(y1 AS BIGINT) AS y1, CAST(x2 AS BIGINT) AS x2, CAST(y2 AS BIGINT) AS y2, cls, text FROM dets")
def proj_box(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detections(spark, sf_dir).select("frame", *[F.col(c).cast("bigint").alias(c) for c in ("ord", "x1", "y1", "x2", "y2")], "cls", "text")


@query("filt_conf", "SELECT l_orderkey AS frame, l_linenumber AS n, l_returnflag AS cls FROM lineitem WHERE l_discount >= 0.05 AND l_returnflag IN ('A', 'R') AND l_linestatus NOT IN ('X') AND l_quantity BETWEEN 10 AND 40 AND l_linestatus IS NOT DISTINCT FROM 'F'")
def filt_conf(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    ok = (c("l_discount") >= F.lit(0.05)) & c("l_returnflag").isin("A", "R") & ~c("l_linestatus").isin("X") & c("l_quantity").between(10, 40) & c("l_linestatus").eqNullSafe(F.lit("F"))
    return table(spark, sf_dir, "lineitem").where(ok).select(c("l_orderkey").alias("frame"), c("l_linenumber").alias("n"), c("l_returnflag").alias("cls"))


@query("filt_text", "SELECT doc_id, source FROM documents WHERE text LIKE '%the%' AND regexp_matches(source, '^src1') AND contains(text, 'ion')")
def filt_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").where(F.col("text").like("%the%") & F.col("source").rlike("^src1") & F.col("text").contains("ion")).select("doc_id", "source")


@query("filt_time", "SELECT o_orderkey AS frame, o_orderkey * 1000 // 24 AS ms FROM orders WHERE o_orderkey * 1000 // 24 BETWEEN 10000 AND 20000")
def filt_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    ms = F.expr("o_orderkey * 1000 div 24")
    return table(spark, sf_dir, "orders").where(ms.between(10000, 20000)).select(F.col("o_orderkey").alias("frame"), ms.alias("ms"))


@query("filt_exists", "SELECT o_orderkey AS frame FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'A')")
def filt_exists(spark: SparkSession, sf_dir: str) -> DataFrame:
    hits = table(spark, sf_dir, "lineitem").where("l_returnflag = 'A'").select("l_orderkey")
    orders = table(spark, sf_dir, "orders")
    return orders.join(hits, orders["o_orderkey"] == hits["l_orderkey"], "left_semi").select(F.col("o_orderkey").alias("frame"))


@query("case_color", "SELECT l_returnflag AS cls, CASE l_returnflag WHEN 'A' THEN '0,0,255' WHEN 'N' THEN '0,255,0' ELSE '255,0,0' END AS bgr, count(*) AS n FROM lineitem GROUP BY ALL")
def case_color(spark: SparkSession, sf_dir: str) -> DataFrame:
    palette = F.create_map(*map(F.lit, ("A", "0,0,255", "N", "0,255,0", "R", "255,0,0")))
    li = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("cls")).agg(F.count("*").alias("n"))
    return li.select("cls", F.try_element_at(palette, F.col("cls")).alias("bgr"), "n")


@query("filt_lateral_alias", "SELECT o_orderkey AS frame, o_orderkey // 60 AS gop, o_orderkey // 60 * 60 AS head, o_orderkey - o_orderkey // 60 * 60 AS dpos FROM orders")
def filt_lateral_alias(spark: SparkSession, sf_dir: str) -> DataFrame:
    table(spark, sf_dir, "orders").createOrReplaceTempView("reelspark_orders")
    return spark.sql("SELECT o_orderkey AS frame, o_orderkey div 60 AS gop, gop * 60 AS head, o_orderkey - head AS dpos FROM reelspark_orders")


@query("sel_star_except", "SELECT o_orderkey, o_custkey, o_orderstatus, o_orderpriority FROM orders")
def sel_star_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").drop("o_totalprice", "o_orderdate")


# -- aggregates ---------------------------------------------------------------------------------------


@query("agg_per_frame", "SELECT l_orderkey AS frame, count(*) AS n, count(*) FILTER (l_returnflag = 'A') AS n_a, count(*) FILTER (l_returnflag = 'N') AS n_n, count(*) FILTER (l_returnflag = 'R') AS n_r FROM lineitem GROUP BY 1")
def agg_per_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    one = lambda k: F.count_if(F.col("l_returnflag") == k).alias(f"n_{k.lower()}")
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("frame")).agg(F.count("*").alias("n"), one("A"), one("N"), one("R"))


@query("agg_sorted_list", WITH_DETS + "SELECT frame, string_agg(cls || ':' || text, ';' ORDER BY ord) AS draw_list FROM dets GROUP BY frame")
def agg_sorted_list(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = detections(spark, sf_dir).groupBy("frame").agg(F.array_sort(F.collect_list(F.struct("ord", F.concat("cls", F.lit(":"), "text").alias("t")))).alias("l"))
    return d.select("frame", F.array_join(F.col("l.t"), ";").alias("draw_list"))


@query("agg_distinct", "SELECT lang, count(DISTINCT source) AS sources, count(*) AS n FROM documents GROUP BY 1")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("lang").agg(F.count_distinct("source").alias("sources"), F.count("*").alias("n"))


@query("agg_approx")
def agg_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches beside exact values; tests hold the error to the stated bounds."""
    e = table(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(
        F.approx_count_distinct("user_id", 0.02).alias("users_hll"), F.count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5, 10_000).alias("median_approx"), F.percentile("value", F.lit(0.5)).alias("median"),
        F.hll_sketch_estimate(F.hll_sketch_agg("user_id", F.lit(14))).alias("users_sketch"), F.count("*").alias("n"),
    )


@query("agg_filter", "SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, CAST(round(sum(CASE WHEN event_type = 'error' THEN CAST(value AS DECIMAL(18, 2)) ELSE 0 END), 2) AS DECIMAL(18, 2)) AS error_value FROM events GROUP BY 1")
def agg_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.sum(F.when(F.col("event_type") == "error", F.col("value").cast("decimal(18,2)")).otherwise(F.lit(0).cast("decimal(18,2)")))
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), v.cast("decimal(18,2)").alias("error_value"))


_GEO = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames by region, nation and status; the two catalogues have a fixed size (25 and 5 rows) and are broadcast."""
    o = table(spark, sf_dir, "orders").select("o_custkey", "o_orderstatus")
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    n, r = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    out = o.join(c, F.col("o_custkey") == F.col("c_custkey"))
    return out.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


@query("agg_rollup", f"SELECT r_name AS region, n_name AS nation, CAST(grouping(r_name) * 2 + grouping(n_name) AS BIGINT) AS level, count(*) AS frames {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _geo(spark, sf_dir).rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("frames"))


@query("agg_cube", f"SELECT r_name AS region, o_orderstatus AS status, CAST(grouping(r_name) * 2 + grouping(o_orderstatus) AS BIGINT) AS level, count(*) AS frames {_GEO} GROUP BY CUBE (r_name, o_orderstatus)")
def agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _geo(spark, sf_dir).cube(F.col("r_name").alias("region"), F.col("o_orderstatus").alias("status")).agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("frames"))


@query("agg_grouping_sets", f"SELECT r_name AS region, n_name AS nation, o_orderstatus AS status, count(*) AS frames {_GEO} GROUP BY GROUPING SETS ((r_name, n_name), (o_orderstatus), ())")
def agg_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _geo(spark, sf_dir).select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("o_orderstatus").alias("status"))
    r, n, s = F.col("region"), F.col("nation"), F.col("status")
    return g.groupingSets([[r, n], [s], []], r, n, s).agg(F.count("*").alias("frames"))


@query("agg_pivot", "SELECT l_returnflag AS cls, count(*) FILTER (l_linestatus = 'F') AS n_f, count(*) FILTER (l_linestatus = 'O') AS n_o FROM lineitem GROUP BY 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("cls")).pivot("l_linestatus", ["F", "O"]).count()
    return p.select("cls", F.coalesce("F", F.lit(0)).alias("n_f"), F.coalesce("O", F.lit(0)).alias("n_o"))


@query("agg_unpivot", "SELECT l_returnflag AS cls, l_linestatus AS status, count(*) AS n FROM lineitem GROUP BY ALL")
def agg_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("cls")).pivot("l_linestatus", ["F", "O"]).count()
    return p.unpivot("cls", ["F", "O"], "status", "n").where("n IS NOT NULL")


@query("agg_minmax_by", WITH_DETS + "SELECT cls, max(frame * 100 + ord) AS last_key, CAST(max(x2 - x1) AS BIGINT) AS widest FROM dets GROUP BY cls")
def agg_minmax_by(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = detections(spark, sf_dir)
    last = F.max_by(F.struct("frame", "ord"), F.struct("frame", "ord"))
    return d.groupBy("cls").agg(last.alias("l"), F.max(F.col("x2") - F.col("x1")).cast("bigint").alias("widest")).select("cls", (F.col("l.frame") * 100 + F.col("l.ord")).alias("last_key"), "widest")


@query("agg_string", "SELECT lang, string_agg(source, ',' ORDER BY source) AS sources FROM (SELECT DISTINCT lang, source FROM documents) GROUP BY 1")
def agg_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("lang").agg(F.array_join(F.array_sort(F.collect_set("source")), ",").alias("sources"))


@query("agg_having", "SELECT l_orderkey // 48 AS seg, count(*) AS n FROM lineitem GROUP BY 1 HAVING count(*) > 190")
def agg_having(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy(F.expr("l_orderkey div 48").alias("seg")).agg(F.count("*").alias("n")).where("n > 190")


@query("agg_moments", "WITH c AS (SELECT l_orderkey // 48 AS seg, l_orderkey, count(*) AS n FROM lineitem GROUP BY 1, 2) SELECT seg, round(avg(n), 6) AS mean, round(coalesce(stddev_samp(n), 0), 6) AS sd, round(quantile_cont(n, 0.5), 6) AS median FROM c GROUP BY seg")
def agg_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n"))
    return c.groupBy(F.expr("l_orderkey div 48").alias("seg")).agg(F.round(F.avg("n"), 6).alias("mean"), F.round(F.coalesce(F.stddev_samp("n"), F.lit(0.0)), 6).alias("sd"), F.round(F.percentile("n", F.lit(0.5)), 6).alias("median"))


# -- sets of frames ----------------------------------------------------------------------------------


def _frames(spark: SparkSession, sf_dir: str, cls: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").where(F.col("l_returnflag") == cls).select(F.col("l_orderkey").alias("frame"))


_A, _R = "SELECT l_orderkey AS frame FROM lineitem WHERE l_returnflag = 'A'", "SELECT l_orderkey AS frame FROM lineitem WHERE l_returnflag = 'R'"
for _name, _sql, _op in (
    ("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b)),
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(_name, f"{_A} {_sql} {_R}")(lambda spark, sf_dir, op=_op: op(_frames(spark, sf_dir, "A"), _frames(spark, sf_dir, "R")))


@query("union_by_name", "SELECT c_custkey AS id, c_name AS name, CAST(NULL AS VARCHAR) AS brand FROM customer UNION ALL SELECT p_partkey, p_name, p_brand FROM part")
def union_by_name(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = table(spark, sf_dir, "customer").select(F.col("c_name").alias("name"), F.col("c_custkey").alias("id"))
    b = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"))
    return a.unionByName(b, allowMissingColumns=True)


# -- order -------------------------------------------------------------------------------------------


@query("sort_multi", "SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id) ORDER BY quality DESC NULLS LAST, doc_id")
def sort_multi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left").orderBy(F.col("quality").desc_nulls_last(), F.col("doc_id").asc_nulls_first())


@query("topk_global", "SELECT o_orderkey AS frame, CAST(floor(o_totalprice) AS BIGINT) AS price FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select(F.col("o_orderkey").alias("frame"), F.floor("o_totalprice").cast("bigint").alias("price"))


@query("limit_offset", "SELECT o_orderkey AS frame FROM orders ORDER BY o_orderkey LIMIT 48 OFFSET 96")
def limit_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("frame")).orderBy("frame").offset(96).limit(48)


@query("sort_within")
def sort_within(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Generation order inside each segment, with no global sort; a test checks every partition."""
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("gen"), F.expr("o_orderkey div 48").alias("seg"))
    return o.repartition(8, "seg").sortWithinPartitions("seg", "gen").withColumn("part", F.spark_partition_id())


@query("shuffle_seeded", "SELECT CAST(row_number() OVER (ORDER BY md5('7:' || CAST(vec_id AS VARCHAR))) - 1 AS BIGINT) AS gen, vec_id AS idx FROM embeddings")
def shuffle_seeded(spark: SparkSession, sf_dir: str) -> DataFrame:
    from reelspark.workloads.access import shuffled

    return shuffled(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("idx"))).select("gen", "idx")


@query("sample_frac", "SELECT o_orderkey AS frame FROM orders WHERE substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 1) = '0'")
def sample_frac(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A repeatable sample of about 1/16: the operator's own meaning, by hash of the key."""
    return table(spark, sf_dir, "orders").where(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 1) == "0").select(F.col("o_orderkey").alias("frame"))
