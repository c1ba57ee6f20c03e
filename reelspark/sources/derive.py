"""Clips derived from the given tables by integer formulas, and the catalogue of sources.

Frame rows are (source_id, idx, raw): raw holds the planes one after another. Everything before the
packing of bytes is a column expression; packing is one Arrow pass without a shuffle.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reelspark.operators.running import numbered, running
from reelspark.session import table

SIDE, GOP_LEN, N_COLLECTION = 16, 60, 100
FRAMES = "source_id string, idx bigint, raw binary"


def main_planes(idx: np.ndarray, price_k: np.ndarray, cust: np.ndarray, status: np.ndarray) -> np.ndarray:
    """(n, 384) bytes of 16 x 16 yuv420p frames."""
    x, y, c = np.arange(SIDE), np.arange(SIDE), np.arange(SIDE // 2)
    luma = (3 * idx[:, None, None] + 7 * x[None, None, :] + 11 * y[None, :, None] + price_k[:, None, None]) % 256
    u = (cust[:, None, None] + 5 * c[None, None, :] + 3 * c[None, :, None]) % 256
    v = (40 * status[:, None, None] + 2 * c[None, None, :] + 9 * c[None, :, None]) % 256
    n = len(idx)
    return np.concatenate([luma.reshape(n, -1), u.reshape(n, -1), v.reshape(n, -1)], 1).astype(np.uint8)


def _order_columns(orders: DataFrame) -> DataFrame:
    status = F.when(F.col("o_orderstatus") == "F", 0).when(F.col("o_orderstatus") == "O", 1).otherwise(2)
    return orders.select(F.col("o_orderkey").alias("i"), F.floor(F.col("o_totalprice") / F.lit(1000.0)).cast("bigint").alias("price_k"), F.col("o_custkey").alias("cust"), status.cast("bigint").alias("status"))


def _packed(rows: DataFrame, pack) -> DataFrame:
    """(source_id, idx, columns...) -> (source_id, idx, raw)."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            raw = pack(*[b.column(k) for k in range(2, b.num_columns)])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([r.tobytes() for r in raw], pa.binary())], names=["source_id", "idx", "raw"])

    return rows.mapInArrow(run, FRAMES)


def _main_pack(*columns: pa.Array) -> np.ndarray:
    return main_planes(*(c.to_numpy(zero_copy_only=False) for c in columns))


def main_frames(spark: SparkSession, sf_dir: str, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """The main clip, or its frames lo..hi: then only those rows are read."""
    orders = table(spark, sf_dir, "orders")
    if lo is not None:
        orders = orders.where(F.col("o_orderkey").between(lo, hi))
    rows = _order_columns(orders).select(F.lit("main").alias("source_id"), F.col("i").alias("idx"), "i", "price_k", "cust", "status")
    return _packed(rows, _main_pack)


def collection_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """100 clips: order i belongs to clip custkey mod 100, at its rank there (counted in blocks of orders)."""
    rows = _order_columns(table(spark, sf_dir, "orders")).withColumn("c", F.pmod("cust", F.lit(N_COLLECTION)))
    rows = numbered(rows, ["c"], "i", "idx", 1 << 18)
    rows = rows.select(F.concat(F.lit("coll/"), F.col("c").cast("string")).alias("source_id"), F.col("idx").cast("bigint").alias("idx"), "i", "price_k", "cust", "status")
    return _packed(rows, _main_pack)


def quantised(embedding: Column) -> Column:
    return F.transform(embedding, lambda e: F.greatest(F.lit(0), F.least(F.lit(255), F.floor((e.cast("double") + F.lit(1.0)) * F.lit(128.0)))).cast("int"))


def _vectors(batch: pa.Array) -> np.ndarray:
    return np.stack(batch.to_numpy(zero_copy_only=False)).astype(np.int64)


def short_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """8 x 8 yuv420p frames from the embeddings."""
    c = np.arange(16)

    def pack(q: pa.Array) -> np.ndarray:
        a = _vectors(q)
        return np.concatenate([a, a[:, 63 - 4 * c], a[:, 4 * c + 2]], 1).astype(np.uint8)

    return _packed(table(spark, sf_dir, "embeddings").select(F.lit("short").alias("source_id"), F.col("vec_id").alias("idx"), quantised(F.col("embedding")).alias("q")), pack)


def mask_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """8 x 8 gray8 masks: set where the quantised component is at least 128."""
    rows = table(spark, sf_dir, "embeddings").select(F.lit("masks").alias("source_id"), F.col("vec_id").alias("idx"), quantised(F.col("embedding")).alias("q"))
    return _packed(rows, lambda q: np.where(_vectors(q) >= 128, 255, 0).astype(np.uint8))


def heat_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(bucket, gx, gy, n): events by hour on an 8 x 8 grid of user and value."""
    e = table(spark, sf_dir, "events")
    hour = F.expr("cast(floor((unix_micros(cast(ts as timestamp)) - unix_micros(timestamp'2024-01-01 00:00:00')) / 3600000000) as bigint)")
    return e.groupBy(hour.alias("bucket"), F.pmod("user_id", F.lit(8)).cast("bigint").alias("gx"), F.pmod(F.floor("value").cast("bigint"), F.lit(8)).alias("gy")).agg(F.count("*").alias("n"))


def heat_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """8 x 8 gray8 rasters: 32 per event, at most 255."""
    cells = F.map_from_entries(F.collect_list(F.struct((F.col("gy") * 8 + F.col("gx")).cast("int"), F.least(F.lit(255), F.col("n") * 32).cast("int"))))
    rows = heat_counts(spark, sf_dir).groupBy("bucket").agg(cells.alias("m"))
    grid = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda k: F.coalesce(F.try_element_at("m", k), F.lit(0)))
    return _packed(rows.select(F.lit("heat").alias("source_id"), F.col("bucket").alias("idx"), grid.alias("q")), lambda q: _vectors(q).astype(np.uint8))


def captions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(source_id, doc_id, start_frame, n_frames): 15 characters a frame, documents in id order within a source. Three numbers a
    document; texts stay where they are."""
    d = table(spark, sf_dir, "documents").select(F.concat(F.lit("cap/"), F.col("source")).alias("source_id"), "doc_id", F.floor((F.col("n_chars") + 14) / 15).cast("bigint").alias("n_frames"))
    return running(d, ["source_id"], "doc_id", "n_frames", "start_frame").select("source_id", "doc_id", "start_frame", "n_frames")


def catalogue(spark: SparkSession, sf_dir: str, gop_len: int = GOP_LEN) -> DataFrame:
    """One row per source; lengths are aggregates, no frame is made."""
    def row(name: Column, w: int, h: int, fmt: str, n: Column, num: int, den: int) -> list[Column]:
        return [name.alias("source_id"), F.lit(w).alias("width"), F.lit(h).alias("height"), F.lit(fmt).alias("fmt"), n.cast("bigint").alias("n_frames"), F.lit(num).alias("fps_num"), F.lit(den).alias("fps_den"), F.lit(gop_len).alias("gop_len")]

    orders, emb = table(spark, sf_dir, "orders"), table(spark, sf_dir, "embeddings")
    main = orders.agg(F.count("*").alias("n")).select(*row(F.lit("main"), 16, 16, "yuv420p", F.col("n"), 24, 1))
    coll = orders.groupBy(F.pmod("o_custkey", F.lit(N_COLLECTION)).alias("c")).agg(F.count("*").alias("n")).select(*row(F.concat(F.lit("coll/"), F.col("c").cast("string")), 16, 16, "yuv420p", F.col("n"), 30000, 1001))
    count = emb.agg(F.count("*").alias("n"))
    short = count.select(*row(F.lit("short"), 8, 8, "yuv420p", F.col("n"), 24, 1))
    masks = count.select(*row(F.lit("masks"), 8, 8, "gray8", F.col("n"), 24, 1))
    caps = table(spark, sf_dir, "documents").groupBy("source").agg(F.sum(F.floor((F.col("n_chars") + 14) / 15)).alias("n")).select(*row(F.concat(F.lit("cap/"), F.col("source")), 16, 16, "yuv420p", F.col("n"), 24, 1))
    heat = heat_counts(spark, sf_dir).agg((F.max("bucket") + 1).alias("n")).select(*row(F.lit("heat"), 8, 8, "gray8", F.col("n"), 1, 1))
    return main.unionByName(coll).unionByName(short).unionByName(masks).unionByName(caps).unionByName(heat)


#: Fixed colours of the three classes, blue-green-red.
COLORS = {"A": (0, 0, 255), "N": (0, 255, 0), "R": (255, 0, 0)}


def detections(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(frame, ord, x1, y1, x2, y2, cls, conf, text, mask_id): ``ord`` ranks a frame's objects by the whole row."""
    li, part = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part").select("p_partkey", "p_name")
    n_masks = table(spark, sf_dir, "embeddings").count()
    # named before the window, so that a filter on the frame passes through it to the scan
    rows = li.join(part, F.col("l_partkey") == F.col("p_partkey"), "left").withColumn("frame", F.col("l_orderkey"))
    order = Window.partitionBy("frame").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
    x1, y1 = F.pmod("l_partkey", F.lit(12)).cast("int"), F.pmod("l_suppkey", F.lit(12)).cast("int")
    return rows.withColumn("ord", F.row_number().over(order)).select(
        "frame", "ord", x1.alias("x1"), y1.alias("y1"),
        F.least(F.lit(15), x1 + 1 + F.pmod(F.col("l_quantity").cast("bigint"), F.lit(8)).cast("int")).alias("x2"), F.least(F.lit(15), y1 + 1 + F.col("l_linenumber")).alias("y2"),
        F.col("l_returnflag").alias("cls"), F.col("l_discount").alias("conf"), F.coalesce("p_name", F.lit("")).alias("text"), F.pmod("l_partkey", F.lit(max(1, n_masks))).alias("mask_id"),
    )


DETECTIONS_SQL = """
SELECT l_orderkey AS frame, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_shipdate) AS ord,
  l_partkey % 12 AS x1, l_suppkey % 12 AS y1, least(15, l_partkey % 12 + 1 + CAST(l_quantity AS BIGINT) % 8) AS x2, least(15, l_suppkey % 12 + 1 + l_linenumber) AS y2,
  l_returnflag AS cls, l_discount AS conf, coalesce(p_name, '') AS text, l_partkey % (SELECT count(*) FROM embeddings) AS mask_id
FROM lineitem LEFT JOIN part ON l_partkey = p_partkey
"""
