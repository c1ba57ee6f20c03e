"""Each filter over all frames of a clip that is already decoded: kernels without scheduler or codec."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.engine import exec as engine
from reelspark.engine import kernels
from reelspark.engine.font import GLYPHS, text_mask
from reelspark.plans.schedule import references
from reelspark.registry import query
from reelspark.session import table
from reelspark.sources import derive
from reelspark.workloads.clips import CLIP_SQL, frames_sql, pixels_sql, task_sources, task_spec


def direct(spark: SparkSession, sf_dir: str, recipe: str) -> DataFrame:
    """Expressions joined with raw frames, evaluated row by row."""
    spec = task_spec(spark, sf_dir, recipe)
    frames = derive.main_frames(spark, sf_dir).unionByName(derive.mask_frames(spark, sf_dir))
    inputs = references(spec).join(frames, ["source_id", "idx"]).join(F.broadcast(task_sources(spark, sf_dir)), "source_id")
    per = inputs.groupBy("spec_id", "gen").agg(F.collect_list(F.struct("source_id", "idx", "raw", "width", "height", "fmt")).alias("frames"))
    return engine.digests(engine.evaluate(spec.join(per, ["spec_id", "gen"]))).select("gen", "md5")


for _name, _recipe in {"f_box": "box", "f_box_corner": "corner", "f_label": "label", "f_color": "color", "f_mask": "mask"}.items():
    query(_name, pixels_sql(_recipe))(lambda spark, sf_dir, recipe=_recipe: direct(spark, sf_dir, recipe))


def _each(spark: SparkSession, sf_dir: str, change) -> DataFrame:
    """(frame, md5) of what ``change`` makes of each main frame (its planes)."""

    def run(it):
        for b in it:
            out = [change(kernels.from_raw(r, 16, 16, "yuv420p")) for r in b.column("raw").to_pylist()]
            md5 = [hashlib.md5(",".join(map(str, o.tobytes())).encode()).hexdigest() for o in out]
            yield pa.RecordBatch.from_arrays([b.column("idx"), pa.array(md5)], names=["frame", "md5"])

    return derive.main_frames(spark, sf_dir).mapInArrow(run, "frame bigint, md5 string")


def _sql(value: str, order: str, where: str = "TRUE", size: int = 16) -> str:
    return f"WITH f AS ({frames_sql()}) SELECT i AS frame, md5(string_agg(CAST({value} AS VARCHAR), ',' ORDER BY {order})) AS md5 FROM f, range({size}) tx(x), range({size}) ty(y) WHERE {where} GROUP BY i"


_Y = "(3 * i + 7 * ({x}) + 11 * ({y}) + p) % 256"
_L = _Y.format(x="x", y="y")
_U, _V = "(c + 5 * (x // 2) + 3 * (y // 2)) % 256", "(40 * k + 2 * (x // 2) + 9 * (y // 2)) % 256"


@query("f_pixfmt", f"WITH f AS ({frames_sql()}), p AS (SELECT i, x, y, {_L} - 16 AS yy, {_U} - 128 AS u, {_V} - 128 AS v FROM f, range(16) tx(x), range(16) ty(y)) SELECT i AS frame, md5(string_agg(concat_ws(',', {CLIP_SQL.format('(298 * yy + 516 * u + 128) >> 8')}, {CLIP_SQL.format('(298 * yy - 100 * u - 208 * v + 128) >> 8')}, {CLIP_SQL.format('(298 * yy + 409 * v + 128) >> 8')}), ',' ORDER BY y, x)) AS md5 FROM p GROUP BY i")
def f_pixfmt(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each(spark, sf_dir, lambda f: kernels.pixfmt(f, "bgr24")[1][0])


@query("f_gray", _sql(_L, "y, x"))
def f_gray(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each(spark, sf_dir, lambda f: kernels.pixfmt(f, "gray8")[1][0])


@query("f_flip", _sql(_Y.format(x="15 - x", y="y"), "y, x"))
def f_flip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each(spark, sf_dir, lambda f: kernels.apply_node("flip", [f], [1], "")[1][0])


@query("f_crop", _sql(_L, "y, x", "x BETWEEN 4 AND 11 AND y BETWEEN 2 AND 5"))
def f_crop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each(spark, sf_dir, lambda f: kernels.apply_node("crop", [f], [4, 2, 8, 4], "")[1][0])


@query("f_resize", _sql(_Y.format(x="2 * x", y="2 * y"), "y, x", size=8))
def f_resize(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each(spark, sf_dir, lambda f: kernels.apply_node("resize", [f], [8, 8, 0], "")[1][0])


_BOX4 = " + ".join(_Y.format(x=f"2 * x + {a}", y=f"2 * y + {b}") for a in (0, 1) for b in (0, 1))


@query("f_resize_box", _sql(f"({_BOX4} + 2) >> 2", "y, x", size=8))
def f_resize_box(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _each(spark, sf_dir, lambda f: kernels.apply_node("resize", [f], [8, 8, 1], "")[1][0])


@query("f_blend", _sql(f"(64 * ({_Y.format(x='15 - x', y='y')}) + 192 * ({_L})) >> 8", "y, x"))
def f_blend(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A frame mixed with its mirror image."""
    return _each(spark, sf_dir, lambda f: kernels.apply_node("blend", [f, kernels.apply_node("flip", [f], [1], "")], [64], "")[1][0])


@query("f_paste", _sql(f"CASE WHEN x < 8 AND y < 8 THEN {_Y.format(x='x + 8', y='y + 8')} ELSE {_L} END", "y, x"))
def f_paste(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A region read and written elsewhere: the lower right quarter over the upper left."""
    return _each(spark, sf_dir, lambda f: kernels.apply_node("paste", [f, kernels.apply_node("crop", [f], [8, 8, 8, 8], "")], [0, 0], "")[1][0])


@query("f_text", "WITH g AS (SELECT * FROM (VALUES " + ", ".join(f"('{ch}', '{dots}')" for ch, dots in GLYPHS.items()) + ") v(ch, dots)), c AS (SELECT p_partkey, unnest(range(1, length(p_name) + 1)) AS k, p_name FROM part), d AS (SELECT p_partkey, 1 + 4 * (k - 1) + d % 3 AS x, 2 + d // 3 AS y FROM c JOIN g ON g.ch = lower(substr(p_name, k, 1)), range(15) r(d) WHERE substr(dots, d + 1, 1) = '1') SELECT p.p_partkey AS id, count(DISTINCT (d.x, d.y)) FILTER (d.x < 16 AND d.y < 16) AS n_set FROM part p LEFT JOIN d ON d.p_partkey = p.p_partkey GROUP BY 1")
def f_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pixels that each part's name covers when written at (1, 2) on a main frame."""

    def run(it):
        for b in it:
            n = [int(np.count_nonzero(text_mask(t or "", 1, 2, 1, 16, 16))) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64())], names=["id", "n_set"])

    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), "p_name").mapInArrow(run, "id bigint, n_set bigint")
