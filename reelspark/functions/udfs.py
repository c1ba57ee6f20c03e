"""User-defined functions where expressions do not reach: vectorised over Arrow, registered for SQL."""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from reelspark.registry import query
from reelspark.session import table
from reelspark.sources import derive


@F.arrow_udf(LongType())
def packed_size(raw: pa.Array) -> pa.Array:
    """Bytes of a frame under the codec's intra packets."""
    return pa.array([None if r is None else len(zlib.compress(r, 1)) for r in raw.to_pylist()], pa.int64())


@F.pandas_udf(LongType())
def luma_sum(raw: pd.Series) -> pd.Series:
    return raw.map(lambda r: int(np.frombuffer(r, np.uint8, 256).sum()))


@query("udf_scalar_arrow")
def udf_scalar_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derive.main_frames(spark, sf_dir).select("idx", packed_size("raw").alias("packed"))


_PIX = """
WITH f AS (SELECT o_orderkey AS i, CAST(floor(o_totalprice / 1000.0) AS BIGINT) AS p, o_custkey AS c, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS k FROM orders)
"""


@query("udf_luma_sum", _PIX + "SELECT i AS idx, CAST(sum((3 * i + 7 * x + 11 * y + p) % 256) AS BIGINT) AS luma FROM f, range(16) t(x), range(16) u(y) GROUP BY 1")
def udf_luma_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derive.main_frames(spark, sf_dir).select("idx", luma_sum("raw").alias("luma"))


@query("udf_kernel", "SELECT vec_id AS idx, CAST(len(list_filter(embedding, lambda e: floor((CAST(e AS DOUBLE) + 1) * 128) >= 128)) AS BIGINT) AS n_set FROM embeddings")
def udf_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A kernel over Arrow batches: set pixels of each mask frame."""

    def run(it):
        for b in it:
            yield pa.RecordBatch.from_arrays([b.column("idx"), pa.array([int(np.count_nonzero(np.frombuffer(r, np.uint8))) for r in b.column("raw").to_pylist()], pa.int64())], names=["idx", "n_set"])

    return derive.mask_frames(spark, sf_dir).mapInArrow(run, "idx bigint, n_set bigint")


@query("udf_group", "SELECT o_orderkey // 60 AS gop_id, count(*) AS n FROM orders GROUP BY 1")
def udf_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode and decode by group; the SQL gives the group sizes that must come back."""
    from reelspark.sources import gopindex

    back = gopindex.decode(gopindex.encode(derive.main_frames(spark, sf_dir)))
    return back.groupBy(F.expr("idx div 60").alias("gop_id")).agg(F.count("*").alias("n"))


@F.pandas_udf(LongType())
def max_difference(a: pd.Series, b: pd.Series) -> int:
    """Largest difference of any byte between two columns of frames."""
    return max((int(np.abs(np.frombuffer(x, np.uint8).astype(int) - np.frombuffer(y, np.uint8)).max()) for x, y in zip(a, b, strict=True)), default=0)


@query("udaf_frame_diff", "SELECT o_orderkey // 480 AS part, CAST(0 AS BIGINT) AS diff FROM orders GROUP BY 1")
def udaf_frame_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lossless codec: the largest difference after a round trip is 0 in every part."""
    from reelspark.sources import gopindex

    frames = derive.main_frames(spark, sf_dir)
    back = gopindex.decode(gopindex.encode(frames, b_run=2)).withColumnRenamed("raw", "again")
    return frames.join(back, ["source_id", "idx"]).groupBy(F.expr("idx div 480").alias("part")).agg(max_difference("raw", "again").alias("diff"))


class ExplodeSpec:
    """One row per node of an expression."""

    def eval(self, gen: int, nodes: list):
        for pos, n in enumerate(nodes):
            yield gen, pos, n["op"], len(n["kids"])


@query("udtf_explode_spec", "SELECT o_orderkey AS gen, CAST(0 AS BIGINT) AS pos, 'ref' AS op, CAST(0 AS BIGINT) AS n_kids FROM orders")
def udtf_explode_spec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from reelspark.lift.relational import sequence_spec

    register(spark)
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("gen"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))
    sequence_spec(o, "clip", 48).createOrReplaceTempView("reelspark_spec")
    return spark.sql("SELECT t.* FROM reelspark_spec, LATERAL reelspark_nodes(gen, nodes) t")


def register(spark: SparkSession) -> None:
    """SQL names: reelspark_packed_size, reelspark_luma_sum, reelspark_extent and the table function reelspark_nodes."""
    spark.udf.register("reelspark_packed_size", packed_size)
    spark.udf.register("reelspark_luma_sum", luma_sum)
    spark.udtf.register("reelspark_nodes", F.udtf(ExplodeSpec, returnType="gen: bigint, pos: bigint, op: string, n_kids: bigint"))


@query("sql_register", _PIX + "SELECT i AS idx, CAST(sum((3 * i + 7 * x + 11 * y + p) % 256) AS BIGINT) AS luma FROM f, range(16) t(x), range(16) u(y) GROUP BY 1")
def sql_register(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    derive.main_frames(spark, sf_dir).createOrReplaceTempView("reelspark_frames")
    return spark.sql("SELECT idx, reelspark_luma_sum(raw) AS luma FROM reelspark_frames")


def digest(raw: bytes) -> str:
    return hashlib.md5(",".join(map(str, raw)).encode()).hexdigest()
