"""Scalar functions on labels, times, pixels and specs, by family; all stay inside the JVM."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.registry import query
from reelspark.session import table


def fmt_timestamp(ms: Column) -> Column:
    """Milliseconds as hh:mm:ss.mmm."""
    d = lambda n: F.expr("cast(0 as bigint)") + F.floor(ms / F.lit(n)).cast("bigint")
    return F.format_string("%02d:%02d:%02d.%03d", d(3_600_000), F.pmod(d(60_000), F.lit(60)), F.pmod(d(1000), F.lit(60)), F.pmod(ms, F.lit(1000)))


STAMP_SQL = "printf('%02d:%02d:%02d.%03d', {0} // 3600000, ({0} // 60000) % 60, ({0} // 1000) % 60, {0} % 1000)"


@query("fn_timestamp", f"SELECT o_orderkey AS frame, {STAMP_SQL.format('(o_orderkey * 1000 // 24)')} AS stamp FROM orders")
def fn_timestamp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("frame"), fmt_timestamp(F.expr("o_orderkey * 1000 div 24")).alias("stamp"))


@query("fn_string", "SELECT p_partkey AS id, upper(p_name) AS up, substr(p_name, 1, 4) AS head, instr(p_name, ' ') AS gap, split_part(p_name, ' ', 1) AS word, regexp_extract(p_brand, '#([0-9]+)', 1) AS brand, regexp_replace(p_name, '[aeiou]', '_', 'g') AS vowels, lpad(CAST(p_size AS VARCHAR), 4, '0') AS size4, translate(p_name, 'abc', 'xyz') AS tr, CAST(levenshtein(p_name, 'red widget') AS BIGINT) AS dist, md5(p_name) AS md5, sha256(p_name) AS sha FROM part")
def fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("p_name")
    return table(spark, sf_dir, "part").select(
        F.col("p_partkey").alias("id"), F.upper(n).alias("up"), F.substring(n, 1, 4).alias("head"), F.instr(n, " ").cast("bigint").alias("gap"), F.split_part(n, F.lit(" "), F.lit(1)).alias("word"), F.regexp_extract("p_brand", "#([0-9]+)", 1).alias("brand"),
        F.regexp_replace(n, "[aeiou]", "_").alias("vowels"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("size4"), F.translate(n, "abc", "xyz").alias("tr"), F.levenshtein(n, F.lit("red widget")).cast("bigint").alias("dist"), F.md5(n).alias("md5"), F.sha2(n, 256).alias("sha"),
    )


@query("fn_datetime", "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour, epoch_us(ts) AS us, datediff('minute', TIMESTAMP '2024-01-01 00:00:00', date_trunc('minute', ts)) AS minutes, strftime(date_trunc('second', ts) + INTERVAL 90 SECOND, '%Y-%m-%d %H:%M:%S') AS later, (epoch_us(ts) - 1704067200000000) * 24 // 1000000 AS frame FROM events")
def fn_datetime(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = F.col("ts").cast("timestamp")
    us = F.unix_micros(t)
    return table(spark, sf_dir, "events").select(
        "event_id", F.date_format(F.date_trunc("hour", t), "yyyy-MM-dd HH:mm:ss").alias("hour"), us.alias("us"), F.timestamp_diff("MINUTE", F.lit("2024-01-01 00:00:00").cast("timestamp"), F.date_trunc("minute", t)).alias("minutes"),
        F.date_format(F.date_trunc("second", t) + F.make_dt_interval(secs=F.lit(90)), "yyyy-MM-dd HH:mm:ss").alias("later"), F.expr("(unix_micros(cast(ts as timestamp)) - 1704067200000000) * 24 div 1000000").alias("frame"),
    )


@query("fn_math", "SELECT o_orderkey AS i, ((o_orderkey - 700) % 3 + 3) % 3 AS pm, CAST(floor(o_totalprice / 1000.0) AS BIGINT) AS fl, CAST(ceil(o_totalprice / 1000.0) AS BIGINT) AS ce, (o_orderkey - 300) >> 3 AS sh, xor(o_orderkey, 3) AS x, o_orderkey & 15 AS a, least(o_orderkey, 100) AS lo, greatest(o_custkey, 50) AS hi, round(sqrt(o_custkey * o_custkey + 9.0), 6) AS hy, CAST(bit_count(o_orderkey) AS BIGINT) AS bits FROM orders")
def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    i, c = F.col("o_orderkey"), F.col("o_custkey")
    return table(spark, sf_dir, "orders").select(
        i.alias("i"), F.pmod(i - 700, F.lit(3)).alias("pm"), F.floor(F.col("o_totalprice") / F.lit(1000.0)).cast("bigint").alias("fl"), F.ceil(F.col("o_totalprice") / F.lit(1000.0)).cast("bigint").alias("ce"), F.shiftright(i - 300, 3).alias("sh"), i.bitwiseXOR(3).alias("x"), i.bitwiseAND(15).alias("a"),
        F.least(i, F.lit(100)).alias("lo"), F.greatest(c, F.lit(50)).alias("hi"), F.round(F.hypot(c.cast("double"), F.lit(3.0)), 6).alias("hy"), F.bit_count(i).cast("bigint").alias("bits"),
    )


@query("fn_array", "WITH l AS (SELECT l_orderkey AS frame, list(l_partkey % 20 ORDER BY l_partkey, l_suppkey, l_linenumber) AS a FROM lineitem GROUP BY 1) SELECT frame, CAST(len(a) AS BIGINT) AS n, CAST(list_sum(list_transform(a, lambda x: x * 2)) AS BIGINT) AS s2, CAST(len(list_filter(a, lambda x: x > 9)) AS BIGINT) AS big, CAST(len(list_distinct(a)) AS BIGINT) AS d, array_to_string(list_sort(list_distinct(a)), ',') AS sorted, array_to_string(a[1:2], ',') AS head, list_contains(a, 7) AS has7 FROM l")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = F.array_sort(F.collect_list(F.struct("l_partkey", "l_suppkey", "l_linenumber")))
    l = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("frame")).agg(F.transform(rows, lambda r: F.pmod(r["l_partkey"], F.lit(20))).alias("a"))  # noqa: E741
    a = F.col("a")
    return l.select(
        "frame", F.size(a).cast("bigint").alias("n"), F.aggregate(F.transform(a, lambda x: x * 2), F.lit(0).cast("bigint"), lambda s, x: s + x).alias("s2"), F.size(F.filter(a, lambda x: x > 9)).cast("bigint").alias("big"), F.size(F.array_distinct(a)).cast("bigint").alias("d"),
        F.array_join(F.array_sort(F.array_distinct(a)), ",").alias("sorted"), F.array_join(F.slice(a, 1, 2), ",").alias("head"), F.exists(a, lambda x: x == 7).alias("has7"),
    )


@query("fn_map", "SELECT o_custkey AS cust, string_agg(o_orderstatus || '=' || n, ',' ORDER BY o_orderstatus) AS counts, CAST(coalesce(sum(n) FILTER (o_orderstatus = 'F'), 0) AS BIGINT) AS f FROM (SELECT o_custkey, o_orderstatus, count(*) AS n FROM orders GROUP BY ALL) GROUP BY 1")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n"))
    m = c.groupBy(F.col("o_custkey").alias("cust")).agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("o_orderstatus", "n")))).alias("m"))
    return m.select("cust", F.array_join(F.transform(F.map_keys("m"), lambda k: F.concat(k, F.lit("="), F.element_at("m", k).cast("string"))), ",").alias("counts"), F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("f"))


@query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, '{\"k\":' || json_extract_string(props, '$.k') || ',\"t\":\"' || event_type || '\"}' AS again FROM events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = F.from_json("props", "k bigint")
    again = F.to_json(F.struct(F.get_json_object("props", "$.k").cast("bigint").alias("k"), F.col("event_type").alias("t")))
    return table(spark, sf_dir, "events").select("event_id", p["k"].alias("k"), again.alias("again"))


@query("fn_variant", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def fn_variant(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("fn_generator", "SELECT p_partkey AS id, CAST(pos - 1 AS BIGINT) AS pos, word FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word, generate_subscripts(string_split(p_name, ' '), 1) AS pos FROM part)")
def fn_generator(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.posexplode(F.split("p_name", " ")).alias("pos", "word")).withColumn("pos", F.col("pos").cast("bigint"))


@query("fn_stack", "SELECT s_suppkey AS id, k, v FROM (SELECT s_suppkey, 'nation' AS k, CAST(s_nationkey AS VARCHAR) AS v FROM supplier UNION ALL SELECT s_suppkey, 'name', s_name FROM supplier)")
def fn_stack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), F.stack(F.lit(2), F.lit("nation"), F.col("s_nationkey").cast("string"), F.lit("name"), F.col("s_name")).alias("k", "v"))


@query("fn_struct", "SELECT o_orderkey AS id, o_custkey AS a, o_orderstatus || '!' AS b FROM orders")
def fn_struct(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = F.named_struct(F.lit("a"), F.col("o_custkey"), F.lit("b"), F.col("o_orderstatus"))
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), s.withField("b", F.concat("o_orderstatus", F.lit("!"))).alias("s")).select("id", "s.*")


@query("fn_binary", "SELECT p_partkey AS id, to_base64(encode(p_name)) AS b64, hex(encode(p_name)) AS hx, decode(unhex(hex(encode(p_name)))) AS back FROM part")
def fn_binary(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = F.encode("p_name", "utf-8")
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.base64(b).alias("b64"), F.hex(b).alias("hx"), F.decode(F.unhex(F.hex(b)), "utf-8").alias("back"))


def iou(a: list[Column], b: list[Column]) -> Column:
    """Overlap over union of two closed boxes (x1, y1, x2, y2)."""
    from reelspark.operators.joins import box_area

    both = box_area(F.greatest(a[0], b[0]), F.greatest(a[1], b[1]), F.least(a[2], b[2]), F.least(a[3], b[3]))
    return both / (box_area(*a) + box_area(*b) - both)


def clip_box(x1: Column, y1: Column, x2: Column, y2: Column, w: int, h: int) -> list[Column]:
    return [F.greatest(F.lit(0), x1), F.greatest(F.lit(0), y1), F.least(F.lit(w - 1), x2), F.least(F.lit(h - 1), y2)]


@query("fn_geometry", "WITH d AS (SELECT l_orderkey AS frame, CAST(l_partkey % 12 AS BIGINT) AS x1, CAST(l_suppkey % 12 AS BIGINT) AS y1, l_linenumber AS n FROM lineitem), e AS (SELECT frame, x1, y1, x1 + n AS x2, y1 + n AS y2 FROM d) SELECT frame, x1, y1, x2, y2, round(CAST(greatest(0, least(x2, 10) - greatest(x1, 4) + 1) * greatest(0, least(y2, 10) - greatest(y1, 4) + 1) AS DOUBLE) / ((x2 - x1 + 1) * (y2 - y1 + 1) + 49 - greatest(0, least(x2, 10) - greatest(x1, 4) + 1) * greatest(0, least(y2, 10) - greatest(y1, 4) + 1)), 9) AS iou, least(15, x2) AS cx2, least(15, y2) AS cy2 FROM e")
def fn_geometry(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("l_linenumber")
    d = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("frame"), F.pmod("l_partkey", F.lit(12)).alias("x1"), F.pmod("l_suppkey", F.lit(12)).alias("y1"), n).select("frame", "x1", "y1", (F.col("x1") + n).alias("x2"), (F.col("y1") + n).alias("y2"))
    box = [F.col(c) for c in ("x1", "y1", "x2", "y2")]
    clipped = clip_box(*box, 16, 16)
    return d.select("frame", *box, F.round(iou(box, [F.lit(4), F.lit(4), F.lit(10), F.lit(10)]), 9).alias("iou"), clipped[2].alias("cx2"), clipped[3].alias("cy2"))


@query("text_extent", "SELECT p_partkey AS id, greatest(0, length(p_name) * 4 - 1) * 2 AS w, CASE WHEN length(p_name) > 0 THEN 10 ELSE 0 END AS h FROM part")
def text_extent(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.length("p_name")
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), (F.greatest(F.lit(0), n * 4 - 1) * 2).cast("bigint").alias("w"), F.when(n > 0, 10).otherwise(0).alias("h"))
