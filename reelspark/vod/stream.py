"""Pushes as a stream into the spec store: checked per micro-batch, stored by batch id, rejects kept apart."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.check import types as check


def ingest(pushes: DataFrame, sources: DataFrame, path: str, checkpoint: str, want: tuple[int, int, str] | None = None, policy: check.Policy = check.Policy()):
    """``pushes``: a stream of spec rows (spec_id, gen, seg, nodes). Returns the started query.

    A batch writes one folder of accepted rows and one of rejects, both by overwrite: a batch that is run again after
    a failure replaces what it wrote. Types are checked against the catalogue by join, policy row by row.
    """

    def batch(df: DataFrame, number: int) -> None:
        df.persist()
        try:
            types = check.infer(df, sources, want).select("spec_id", "gen", "ok", "err")
            rules = check.enforce(df, policy).select("spec_id", "gen", F.col("ok").alias("fits"), F.col("err").alias("breach"))
            seen = df.dropDuplicates(["spec_id", "gen"]).join(types.dropDuplicates(["spec_id", "gen"]), ["spec_id", "gen"]).join(rules.dropDuplicates(["spec_id", "gen"]), ["spec_id", "gen"])
            seen.where("ok AND fits").select("spec_id", "gen", "seg", "nodes").write.mode("overwrite").parquet(f"{path}/specs/batch={number}")
            seen.where("NOT (ok AND fits)").select("spec_id", "gen", F.when(~F.col("ok"), F.col("err")).otherwise(F.col("breach")).alias("err")).write.mode("overwrite").parquet(f"{path}/rejects/batch={number}")
        finally:
            df.unpersist()

    return pushes.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
