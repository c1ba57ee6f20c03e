"""A Python data source over stored GOPs: ``spark.read.format("reelframes")``, batch and stream.

Options: path (a folder of GOP files written by ``stored``), gop_len. A partition is a file of one GOP range; filters on
source_id and idx are taken over, so that GOPs outside are neither opened nor decoded. Files are listed and
read through pyarrow's file systems, which know local and object stores.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

SCHEMA = "source_id string, idx bigint, raw binary"


class GopRange(InputPartition):
    def __init__(self, file: str, lo: int, hi: int, source: str | None):
        self.file, self.lo, self.hi, self.source = file, lo, hi, source


class FrameReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.lo, self.hi, self.source = path, 0, 1 << 62, None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            name = f.attribute[0] if len(f.attribute) == 1 else None
            if name == "idx" and isinstance(f, GreaterThanOrEqual):
                self.lo = max(self.lo, f.value)
            elif name == "idx" and isinstance(f, GreaterThan):
                self.lo = max(self.lo, f.value + 1)
            elif name == "idx" and isinstance(f, LessThan):
                self.hi = min(self.hi, f.value - 1)
            elif name == "idx" and isinstance(f, LessThanOrEqual):
                self.hi = min(self.hi, f.value)
            elif name == "idx" and isinstance(f, EqualTo):
                self.lo, self.hi = max(self.lo, f.value), min(self.hi, f.value)
            elif name == "source_id" and isinstance(f, EqualTo):
                self.source = f.value
            else:
                yield f

    def partitions(self) -> list[GopRange]:
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.path)
        files = [f.path for f in system.get_file_info(fs.FileSelector(root, recursive=True)) if f.path.endswith(".parquet")]
        out = []
        for f in sorted(files):
            part = dict(x.split("=", 1) for x in f.split("/") if "=" in x)
            low = int(part.get("lo", 0))
            if low <= self.hi and low + int(part.get("span", 1 << 62)) > self.lo:
                out.append(GopRange(f, self.lo, self.hi, self.source))
        return out or [GopRange("", 0, -1, None)]

    def read(self, partition: GopRange) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq
        from pyarrow import fs

        from reelspark.sources import codec

        if not partition.file:
            return
        system, _ = fs.FileSystem.from_uri(self.path)
        for g in pq.read_table(partition.file, filesystem=system, columns=["source_id", "first_idx", "n", "packets"], partitioning=None).to_pylist():
            if (partition.source and g["source_id"] != partition.source) or g["first_idx"] > partition.hi or g["first_idx"] + g["n"] <= partition.lo:
                continue
            wanted = [p["dpos"] for p in g["packets"] if partition.lo <= p["idx"] <= partition.hi]
            rows = [(i, r) for i, r in codec.decode(g["packets"], max(wanted)) if partition.lo <= i <= partition.hi]
            yield pa.RecordBatch.from_arrays([pa.array([g["source_id"]] * len(rows)), pa.array([i for i, _ in rows], pa.int64()), pa.array([r for _, r in rows], pa.binary())], names=["source_id", "idx", "raw"])


class FrameSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "reelframes"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> FrameReader:
        return FrameReader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(FrameSource)


def stored(spark: SparkSession, sf_dir: str, gops_per_file: int = 8) -> str:
    """Writes the main clip's GOPs as files of a known index range; returns the folder."""
    from pyspark.sql import functions as F

    from reelspark.sources import derive, gopindex
    from reelspark.sources.io import shared_folder

    path = shared_folder(spark, "gops")
    span = gops_per_file * derive.GOP_LEN
    g = gopindex.encode(derive.main_frames(spark, sf_dir)).withColumn("lo", F.expr(f"first_idx div {span} * {span}")).withColumn("span", F.lit(span))
    g.repartition("lo").write.partitionBy("lo", "span").parquet(path)
    return path
