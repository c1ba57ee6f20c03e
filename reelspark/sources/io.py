"""Readers and writers around clips: files, specs, segments, playlists, paths and blocks."""

from __future__ import annotations

import os
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from reelspark.registry import query
from reelspark.session import table


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder that all executors share: under spark.checkpoint.dir. Where that is unset a local session may use a folder of its
    own (tests); on a cluster it would be another one on every machine, so it is an error."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        import tempfile

        base = "file://" + tempfile.mkdtemp(prefix="reelspark-")
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def pruned(spark: SparkSession, sf_dir: str, name: str, cols: list[str], where: Column | None = None) -> DataFrame:
    """Only the named columns, with the predicate at the scan."""
    df = table(spark, sf_dir, name)
    return (df.where(where) if where is not None else df).select(*cols)


@query("scan_parquet", "SELECT l_orderkey, l_returnflag FROM lineitem WHERE l_orderkey >= 1000 AND l_returnflag = 'R'")
def scan_parquet(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pruned(spark, sf_dir, "lineitem", ["l_orderkey", "l_returnflag"], (F.col("l_orderkey") >= 1000) & (F.col("l_returnflag") == "R"))


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """Explicit schema; rows that don't fit are kept with their text in ``_corrupt``."""
    return spark.read.csv(path, schema=schema + ", _corrupt string", header=True, mode="PERMISSIVE", columnNameOfCorruptRecord="_corrupt")


@query("scan_csv", "SELECT l_orderkey AS frame, l_partkey % 12 AS x1, l_returnflag AS cls FROM lineitem")
def scan_csv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A script's own input: detections through a CSV file and back."""
    path = shared_folder(spark, "csv")
    table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("frame"), F.pmod("l_partkey", F.lit(12)).alias("x1"), F.col("l_returnflag").alias("cls")).write.csv(path, header=True)
    return read_csv(spark, path, "frame bigint, x1 bigint, cls string").select("frame", "x1", "cls")


@query("scan_json", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def scan_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy(F.from_json("props", "k bigint")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("scan_text", "SELECT conv_id, turn, length(text) AS chars FROM conversations WHERE role = 'assistant'")
def scan_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scripts as text files, one file a script when read back with wholetext; here the length of each."""
    path = shared_folder(spark, "scripts")
    rows = table(spark, sf_dir, "conversations").where("role = 'assistant'").select("conv_id", "turn", F.hex(F.encode("text", "utf-8")).alias("value"))
    rows.write.partitionBy("conv_id", "turn").text(path)
    back = spark.read.schema("value string, conv_id bigint, turn bigint").text(path)
    return back.select("conv_id", "turn", F.length(F.decode(F.unhex("value"), "utf-8")).cast("bigint").alias("chars"))


@query("src_frames", "SELECT 'main' AS source_id, o_orderkey AS idx, CAST(384 AS BIGINT) AS bytes FROM orders")
def src_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Python data source: all frames; filters on source and index are pushed to it (tested apart)."""
    from reelspark.sources import framesource

    framesource.register(spark)
    gops = framesource.stored(spark, sf_dir)
    df = spark.read.format("reelframes").option("path", gops).option("gop_len", "60").load()
    return df.select("source_id", "idx", F.length("raw").cast("bigint").alias("bytes"))


# -- sinks -----------------------------------------------------------------------------------------------


def append_spec(spec: DataFrame, path: str) -> None:
    """Spec rows by (spec, segment): a segment request then reads its own partition only."""
    spec.write.mode("append").partitionBy("spec_id", "seg").parquet(path)


def write_segments(segments: DataFrame, path: str) -> None:
    """Idempotent: a repeated write of a segment replaces that partition and no other."""
    segments.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("spec_id", "seg").parquet(path)


@query("sink_spec", "SELECT o_orderkey AS gen, o_orderkey // 48 AS seg FROM orders")
def sink_spec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from reelspark.lift.relational import sequence_spec

    path = shared_folder(spark, "spec")
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("gen"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))
    append_spec(sequence_spec(o, "clip", 48), path)
    return spark.read.parquet(path).where("spec_id = 'clip'").select("gen", F.col("seg").cast("bigint").alias("seg"))


@query("sink_segments", "SELECT o_orderkey // 1200 AS seg, CAST(sum(o_custkey) + CASE WHEN (o_orderkey // 1200) % 3 = 1 THEN 7 ELSE 0 END AS BIGINT) AS v FROM orders GROUP BY o_orderkey // 1200")
def sink_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A value for every run of 1,200 frames; every third is written again with another value: one row per segment remains."""
    path = shared_folder(spark, "segments")
    rows = table(spark, sf_dir, "orders").groupBy(F.expr("o_orderkey div 1200").alias("seg")).agg(F.sum("o_custkey").alias("v")).select(F.lit("s").alias("spec_id"), "seg", "v")
    write_segments(rows, path)
    write_segments(rows.where("seg % 3 = 1").withColumn("v", F.col("v") + 7), path)
    return spark.read.parquet(path).select(F.col("seg").cast("bigint").alias("seg"), "v")


def resolve(path: Column) -> Column:
    """Storage place of a clip named by a bare key or a URL; other schemes stay as they are."""
    scheme = F.regexp_extract(path, r"^([a-z][a-z0-9+.-]*)://", 1)
    host, file = F.regexp_extract(path, r"^[a-z][a-z0-9+.-]*://([^/?#]+)", 1), F.regexp_extract(path, r"^[a-z][a-z0-9+.-]*://[^/?#]+(/[^?#]*)", 1)
    return F.when(scheme.isin("http", "https"), F.concat(F.lit("store/"), host, file, F.lit(".reel"))).when(scheme == "", F.concat(F.lit("clips/"), path, F.lit(".reel"))).otherwise(path)


@query("path_mapping", "SELECT page_id, 'store/' || regexp_extract(url, '^[a-z][a-z0-9+.-]*://([^/?#]+)', 1) || regexp_extract(url, '^[a-z][a-z0-9+.-]*://[^/?#]+(/[^?#]*)', 1) || '.reel' AS place FROM pages")
def path_mapping(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", resolve(F.col("url")).alias("place"))


# -- shared block cache -------------------------------------------------------------------------------


def accesses(spark: SparkSession, sf_dir: str, packet: int = 700) -> DataFrame:
    """Byte ranges that segment requests read: (at, user, seg) from events, GOP packets laid end to end."""
    e = table(spark, sf_dir, "events").select("event_id", F.col("user_id").alias("source"), F.pmod(F.get_json_object("props", "$.k").cast("bigint"), F.lit(50)).alias("seg"))
    return e.withColumns({"lo": F.col("seg") * 60 * packet, "hi": (F.col("seg") + 1) * 60 * packet - 1})


def block_touches(reads: DataFrame, block: int) -> DataFrame:
    return reads.withColumn("block", F.explode(F.sequence(F.expr(f"lo div {block}"), F.expr(f"hi div {block}")))).select("event_id", "source", "block")


_BLOCKS = "WITH a AS (SELECT event_id, user_id AS source, (CAST(json_extract(props, '$.k') AS BIGINT) % 50) * 42000 AS lo FROM events), t AS (SELECT source, unnest(range(lo // 65536, (lo + 41999) // 65536 + 1)) AS block FROM a)"


@query("block_hit", _BLOCKS + " SELECT count(*) AS requests, count(*) - count(DISTINCT (source, block)) AS hits FROM t")
def block_hit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits of a cache without limit: all touches but each block's first."""
    per = block_touches(accesses(spark, sf_dir), 65_536).groupBy("source", "block").agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("requests"), F.sum(F.col("n") - 1).alias("hits"))


@query("block_cache_lru")
def block_cache_lru(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits of bounded LRU caches, one per source host group, by capacity (simulated in request order)."""
    import pandas as pd

    def run(t: pd.DataFrame) -> pd.DataFrame:
        from collections import OrderedDict

        t = t.sort_values(["event_id", "block"])
        out = []
        for cap in (4, 16, 64):
            cache: OrderedDict = OrderedDict()
            hits = 0
            for key in zip(t["source"], t["block"], strict=True):
                if key in cache:
                    hits += 1
                    cache.move_to_end(key)
                else:
                    cache[key] = None
                    if len(cache) > cap:
                        cache.popitem(last=False)
            out.append((int(t["host"].iloc[0]), cap, len(t), hits))
        return pd.DataFrame(out, columns=["host", "capacity", "requests", "hits"])

    touches = block_touches(accesses(spark, sf_dir), 65_536).withColumn("host", F.pmod("source", F.lit(16)))
    return touches.groupBy("host").applyInPandas(run, "host bigint, capacity int, requests bigint, hits bigint")


def file_stream(spark: SparkSession, folder: str, schema: StructType | str, per_trigger: int = 1) -> DataFrame:
    """A push log as a stream of files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(folder)


def local_rank(frames: DataFrame) -> DataFrame:
    return frames.withColumn("local", F.row_number().over(Window.partitionBy("source_id").orderBy("idx")) - 1)


def scheme_of(path: str) -> str:
    return path.split("://", 1)[0] if "://" in path else "file"


__all__ = ["accesses", "append_spec", "file_stream", "read_csv", "resolve", "shared_folder", "write_segments", "os"]
