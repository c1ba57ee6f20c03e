"""Specs of the annotation tasks over the main clip, and the SQL that recomputes their pixels."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.engine.font import GLYPHS
from reelspark.lift import relational
from reelspark.session import table
from reelspark.sources import derive, gopindex
from reelspark.sources.derive import DETECTIONS_SQL, GOP_LEN

SEG = 48  # two seconds at 24 frames per second
TASKS = {"w_label": "label", "w_box_label": "box_label", "w_corner_label": "corner_label", "w_color_label": "color_label", "w_mask_label": "mask_label"}


def main_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("gen"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))


def task_spec(spark: SparkSession, sf_dir: str, recipe: str, conversion: str = "lazy", frames: DataFrame | None = None, needed: bool = False, stored: bool = False) -> DataFrame:
    """``stored``: from ``stored_lists``, for those who need many specs of one clip."""
    if stored:
        return relational.expressed(stored_lists(spark, sf_dir), recipe, recipe, SEG, conversion=conversion, needed=needed)
    return relational.annotate(frames if frames is not None else main_index(spark, sf_dir), derive.detections(spark, sf_dir), recipe, recipe, SEG, conversion=conversion, needed=needed)


def segment_inputs(spark: SparkSession, sf_dir: str, recipe: str, seg: int) -> tuple[DataFrame, DataFrame]:
    """Spec and GOPs of one segment: the generation range reaches both scans, so cost doesn't depend on the clip's length."""
    lo, hi = seg * SEG, (seg + 1) * SEG - 1
    frames = main_index(spark, sf_dir).where(F.col("gen").between(lo, hi))
    dets = derive.detections(spark, sf_dir).where(F.col("frame").between(lo, hi))
    spec = relational.annotate(frames, dets, recipe, recipe, SEG)
    return spec, gopindex.encode(derive.main_frames(spark, sf_dir, lo // GOP_LEN * GOP_LEN, hi // GOP_LEN * GOP_LEN + GOP_LEN - 1))


def task_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The (two) rows of the catalogue that annotation tasks use."""
    from reelspark.model.schemas import SOURCES

    n, m = table(spark, sf_dir, "orders").count(), table(spark, sf_dir, "embeddings").count()
    return spark.createDataFrame([("main", 16, 16, "yuv420p", n, 24, 1, GOP_LEN), ("masks", 8, 8, "gray8", m, 24, 1, GOP_LEN)], SOURCES)


_STORED: dict[tuple, str] = {}


def stored_gops(spark: SparkSession, sf_dir: str, source: str, gop_len: int = GOP_LEN, **kw) -> DataFrame:
    """A clip's GOPs, encoded and written once a session (as a deployment has them), in order, so that readers prune by GOP."""
    from reelspark.model.schemas import GOPS
    from reelspark.sources.io import shared_folder

    key = (spark.sparkContext.applicationId, sf_dir, source, gop_len, *sorted(kw.items()))
    if key not in _STORED:
        frames = {"main": derive.main_frames, "masks": derive.mask_frames, "short": derive.short_frames}[source](spark, sf_dir)
        path = shared_folder(spark, f"gops-{source}")
        gopindex.encode(frames, gop_len, **kw).sortWithinPartitions("gop_id").write.parquet(path)
        _STORED[key] = path
    return spark.read.schema(GOPS).parquet(_STORED[key])


def stored_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main clip's generations with the lists of their detections, joined and written once a session."""
    from reelspark.sources.io import shared_folder

    key = (spark.sparkContext.applicationId, sf_dir, "lists")
    if key not in _STORED:
        path = shared_folder(spark, "lists")
        many = int(spark.conf.get("spark.sql.shuffle.partitions"))
        relational.listed(main_index(spark, sf_dir), derive.detections(spark, sf_dir)).repartition(many, F.expr(f"gen div {16 * SEG}")).write.parquet(path)
        _STORED[key] = path
    return spark.read.parquet(_STORED[key])


def stored_detections(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``derive.detections`` of the main clip's frames, from ``stored_lists``."""
    return stored_lists(spark, sf_dir).select(F.col("gen").alias("frame"), F.inline("dets"))


def task_gops(spark: SparkSession, sf_dir: str, recipe: str, gop_len: int = GOP_LEN, **kw) -> DataFrame:
    out = stored_gops(spark, sf_dir, "main", gop_len, **kw)
    return out.unionByName(stored_gops(spark, sf_dir, "masks", gop_len, **kw)) if "mask" in recipe else out


_PRIMS = {
    "tag": "SELECT frame, ord * 10 + 2 AS seq, 'fill' AS kind, x1, y1, x1 + 4 * length(text) AS x2, y1 + 6 AS y2, b, g, r, text, mask_id FROM d UNION ALL SELECT frame, ord * 10 + 3, 'text', x1 + 1, y1 + 1, x1 + 4 * length(text), y1 + 5, 255, 255, 255, text, mask_id FROM d",
    "box": "SELECT frame, ord * 10 + 1 AS seq, 'box' AS kind, x1, y1, x2, y2, b, g, r, text, mask_id FROM d",
    "corners": "SELECT frame, ord * 10 + 1 AS seq, 'corners' AS kind, x1, y1, x2, y2, b, g, r, text, mask_id FROM d",
    "tint": "SELECT frame, ord * 10 + 1 AS seq, 'tint' AS kind, x1, y1, x2, y2, b, g, r, text, mask_id FROM d",
    "mask": "SELECT frame, ord * 10 + 1 AS seq, 'mask' AS kind, 0 AS x1, 0 AS y1, 15 AS x2, 15 AS y2, b, g, r, text, mask_id FROM d",
}
_PARTS = {"label": ["tag"], "box": ["box"], "box_label": ["box", "tag"], "corner": ["corners"], "mask": ["mask"], "corner_label": ["corners", "tag"], "color": ["tint"], "color_label": ["tint", "tag"], "mask_label": ["mask", "tag"]}


def frames_sql(where: str = "TRUE") -> str:
    return f"SELECT o_orderkey AS i, CAST(floor(o_totalprice / 1000.0) AS BIGINT) AS p, o_custkey AS c, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS k FROM orders WHERE {where}"


CLIP_SQL = "least(255, greatest(0, {0}))"


def pixels_sql(recipe: str | None, where: str = "TRUE", eager: bool = False) -> str:
    """md5 per generation of the rendered planes: base pixels, then the draws that cover each pixel in order."""
    prims = " UNION ALL ".join(_PRIMS[p] for p in _PARTS[recipe]) if recipe else "SELECT * FROM (" + _PRIMS["box"] + ") WHERE FALSE"
    glyphs = ", ".join(f"('{ch}', '{dots}')" for ch, dots in GLYPHS.items())
    clip = CLIP_SQL.format
    reduce = "list_reduce(list_prepend({0}, coalesce(o{1}, [])), lambda a, o: CASE WHEN o >= 1000 THEN (96 * (o - 1000) + 160 * a) >> 8 ELSE o END)"
    touched = "TRUE" if eager else "i IN (SELECT frame FROM d)"
    return f"""
WITH dets AS ({DETECTIONS_SQL}), d AS (SELECT *, CASE cls WHEN 'R' THEN 255 ELSE 0 END AS b, CASE cls WHEN 'N' THEN 255 ELSE 0 END AS g, CASE cls WHEN 'A' THEN 255 ELSE 0 END AS r FROM dets WHERE frame IN (SELECT i FROM ({frames_sql(where)}))),
f AS ({frames_sql(where)}), prims AS ({prims}), glyphs AS (SELECT * FROM (VALUES {glyphs}) v(ch, dots)),
base AS (SELECT i, x, y, (3 * i + 7 * x + 11 * y + p) % 256 AS yy, (c + 5 * (x // 2) + 3 * (y // 2)) % 256 AS uu, (40 * k + 2 * (x // 2) + 9 * (y // 2)) % 256 AS vv FROM f, range(16) tx(x), range(16) ty(y)),
cover AS (SELECT frame, seq, x, y, kind, b, g, r FROM prims, range(16) tx(x), range(16) ty(y) WHERE x BETWEEN x1 AND x2 AND y BETWEEN y1 AND y2 AND CASE kind WHEN 'fill' THEN TRUE WHEN 'tint' THEN TRUE
  WHEN 'box' THEN x = x1 OR x = x2 OR y = y1 OR y = y2
  WHEN 'corners' THEN (x = x1 OR x = x2 OR y = y1 OR y = y2) AND (x < x1 + 3 OR x > x2 - 3) AND (y < y1 + 3 OR y > y2 - 3)
  WHEN 'mask' THEN FALSE
  ELSE (x - x1) % 4 < 3 AND substr((SELECT dots FROM glyphs WHERE ch = lower(substr(text, CAST((x - x1) // 4 + 1 AS BIGINT), 1))), CAST((y - y1) * 3 + (x - x1) % 4 + 1 AS BIGINT), 1) = '1' END
  UNION ALL SELECT frame, seq, x, y, 'tint', b, g, r FROM prims JOIN embeddings ON vec_id = mask_id, range(16) tx(x), range(16) ty(y) WHERE kind = 'mask' AND floor((CAST(embedding[CAST(8 * (y // 2) + x // 2 + 1 AS BIGINT)] AS DOUBLE) + 1) * 128) >= 128),
ops AS (SELECT frame, x, y, list(CASE kind WHEN 'tint' THEN 1000 ELSE 0 END + b ORDER BY seq) AS ob, list(CASE kind WHEN 'tint' THEN 1000 ELSE 0 END + g ORDER BY seq) AS og, list(CASE kind WHEN 'tint' THEN 1000 ELSE 0 END + r ORDER BY seq) AS o_r FROM cover GROUP BY ALL),
bgr AS (SELECT *, {clip("(298 * (yy - 16) + 516 * (uu - 128) + 128) >> 8")} AS b0, {clip("(298 * (yy - 16) - 100 * (uu - 128) - 208 * (vv - 128) + 128) >> 8")} AS g0, {clip("(298 * (yy - 16) + 409 * (vv - 128) + 128) >> 8")} AS r0 FROM base),
drawn AS (SELECT bgr.i, bgr.x, bgr.y, yy, uu, vv, {touched} AS touched, {reduce.format("b0", "b")} AS b, {reduce.format("g0", "g")} AS g, {reduce.format("r0", "_r")} AS r FROM bgr LEFT JOIN ops ON ops.frame = bgr.i AND ops.x = bgr.x AND ops.y = bgr.y),
luma AS (SELECT i, string_agg(CAST(CASE WHEN touched THEN {clip("((66 * r + 129 * g + 25 * b + 128) >> 8) + 16")} ELSE yy END AS VARCHAR), ',' ORDER BY y, x) AS s FROM drawn GROUP BY i),
blocks AS (SELECT i, x // 2 AS cx, y // 2 AS cy, bool_or(touched) AS touched, min(uu) AS uu, min(vv) AS vv, sum(b) AS b, sum(g) AS g, sum(r) AS r FROM drawn GROUP BY ALL),
chroma AS (SELECT i, string_agg(CAST(CASE WHEN touched THEN {clip("((CAST(-38 * r - 74 * g + 112 * b + 512 AS BIGINT)) >> 10) + 128")} ELSE uu END AS VARCHAR), ',' ORDER BY cy, cx) AS u, string_agg(CAST(CASE WHEN touched THEN {clip("((CAST(112 * r - 94 * g - 18 * b + 512 AS BIGINT)) >> 10) + 128")} ELSE vv END AS VARCHAR), ',' ORDER BY cy, cx) AS v FROM blocks GROUP BY i)
SELECT i AS gen, md5(s || ',' || u || ',' || v) AS md5 FROM luma JOIN chroma USING (i)
"""
