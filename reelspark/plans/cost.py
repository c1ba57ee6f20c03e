"""Choice between the two decode plans, from index statistics alone."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.plans.schedule import indexed, located


@dataclass(frozen=True)
class Costs:
    network: float = 1.0  # per byte
    decode: float = 4.0  # per byte of decoded frame


def statistics(refs: DataFrame, gop_len: int | None, frame_bytes: int, packed_bytes: float, gops: DataFrame | None = None) -> DataFrame:
    """One row: references, touched GOPs, segments per GOP (rho), least decodes."""
    at = located(refs, gop_len) if gop_len else indexed(refs, gops)
    per_gop = at.groupBy("source_id", "gop_id").agg(F.count_distinct("spec_id", "seg").alias("segments"), (F.max("dpos") + 1).alias("deep"))
    n_refs = at.agg(F.count("*").alias("refs"))
    g = per_gop.agg(F.coalesce(F.avg("segments"), F.lit(0.0)).alias("rho"), F.coalesce(F.sum("deep"), F.lit(0)).alias("least"), F.count("*").alias("gops"))
    return n_refs.join(g, F.lit(True)).withColumns({"frame_bytes": F.lit(frame_bytes), "packed_bytes": F.lit(float(packed_bytes)) * (F.col("gops") * gop_len if gop_len else F.col("least"))})


def choose(refs: DataFrame, gop_len: int | None, frame_bytes: int, packed_bytes: float = 100.0, costs: Costs = Costs(), gops: DataFrame | None = None) -> DataFrame:
    """The statistics with both estimates and the plan: 'segment_local' or 'gop_exchange'."""
    s = statistics(refs, gop_len, frame_bytes, packed_bytes, gops)
    local = F.col("rho") * F.col("packed_bytes") * costs.network + F.col("rho") * F.col("least") * frame_bytes * costs.decode
    exchange = (F.col("packed_bytes") + F.col("refs") * frame_bytes) * costs.network + F.col("least") * frame_bytes * costs.decode
    return s.withColumns({"local_cost": F.round(local, 3), "exchange_cost": F.round(exchange, 3)}).withColumn("plan", F.when(F.col("local_cost") < F.col("exchange_cost"), "segment_local").otherwise("gop_exchange"))
