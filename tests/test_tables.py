"""Studies run over a given table: other rows, other results."""

import pytest
from pyspark.sql import functions as F

from reelspark import registry
from reelspark.workloads import access

registry.load()


@pytest.fixture(scope="module")
def sparse_keys(spark, sf_dir, tmp_path_factory):
    """Orders whose keys are three apart."""
    d = str(tmp_path_factory.mktemp("keys"))
    spark.read.parquet(f"{sf_dir}/orders.parquet").withColumn("o_orderkey", F.col("o_orderkey") * 3).write.parquet(f"{d}/orders.parquet")
    return d


def test_schedules_come_from_the_table(spark, sf_dir, sparse_keys):
    assert access.dense(spark, sf_dir) == access.dense_schedules()
    assert access.dense(spark, sparse_keys)["every"] == [[3 * i] for i in range(500)]


@pytest.mark.parametrize("name", ["admission_trace", "base_no_abandon", "base_reorder_stream", "m_makespan", "m_parallel_eff", "w_dense_evict", "w_prefetch", "w_sparse_bounds"])
def test_study_depends_on_the_table(spark, sf_dir, sparse_keys, name):
    here, there = (sorted(map(str, registry.QUERIES[name](spark, d).collect())) for d in (sf_dir, sparse_keys))
    assert here != there


@pytest.mark.parametrize("name", ["m_fps_by_res", "w_resolution"])
def test_kernels_are_timed_on_frames_of_the_clip(spark, sparse_keys, tmp_path, name):
    rows = registry.QUERIES[name](spark, sparse_keys).collect()
    assert len(rows) == 8 and all(r["equal"] for r in rows)
    spark.read.parquet(f"{sparse_keys}/orders.parquet").where("false").write.parquet(f"{tmp_path}/orders.parquet")
    assert {r["frames_per_second"] for r in registry.QUERIES[name](spark, str(tmp_path)).collect()} == {0.0}


def test_pools_of_the_tables_clips(spark, sf_dir):
    n = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.pmod("o_custkey", F.lit(100))).distinct().count()
    assert registry.QUERIES["w_pool_bytes"](spark, sf_dir).count() == 3 * n
