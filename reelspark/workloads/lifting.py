"""From scripts and tables to checked, interned specs; schedules and their set forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.check import types as check
from reelspark.lift import frontends, relational, rewrite, shim
from reelspark.model.expr import canonical
from reelspark.plans import schedule as plan
from reelspark.registry import query
from reelspark.session import table
from reelspark.sources import derive
from reelspark.sources.derive import DETECTIONS_SQL
from reelspark.spec import intern as interning
from reelspark.workloads.clips import SEG, task_sources, task_spec

#: SQL of the box-and-label expressions: one text per node, in post-order.
NODES_SQL = f"""dets AS ({DETECTIONS_SQL}),
d AS (SELECT *, CASE cls WHEN 'A' THEN '0,0,255' WHEN 'N' THEN '0,255,0' ELSE '255,0,0' END AS col, 1 + (ord - 1) * 3 AS prev FROM dets),
per AS (SELECT frame, count(*) AS n FROM dets GROUP BY 1),
nodes AS (
  SELECT o_orderkey AS gen, CAST(0 AS BIGINT) AS pos, 'ref(|' || o_orderkey || '|main)' AS t FROM orders
  UNION ALL SELECT frame, 1, 'pixfmt(0||bgr24)' FROM per
  UNION ALL SELECT frame, prev + 1, 'box(' || prev || '|' || concat_ws(',', x1, y1, x2, y2, col, 1) || '|)' FROM d
  UNION ALL SELECT frame, prev + 2, 'box(' || (prev + 1) || '|' || concat_ws(',', x1, y1, x1 + 4 * length(text), y1 + 6, col, -1) || '|)' FROM d
  UNION ALL SELECT frame, prev + 3, 'text(' || (prev + 2) || '|' || concat_ws(',', x1 + 1, y1 + 1, 255, 255, 255, 1) || '|' || text || ')' FROM d
  UNION ALL SELECT frame, 2 + 3 * n, 'pixfmt(' || (1 + 3 * n) || '||yuv420p)' FROM per)"""
_LIFT = f"WITH {NODES_SQL} SELECT gen, count(*) AS n_nodes, count(*) FILTER (t LIKE 'box(%' OR t LIKE 'text(%') AS n_draws, md5(string_agg(t, ';' ORDER BY pos)) AS expr_md5 FROM nodes GROUP BY gen"


def _lift_columns(spec: DataFrame) -> DataFrame:
    draws = F.size(F.filter("nodes", lambda n: n["op"].isin("box", "text")))
    return spec.select("gen", F.size("nodes").cast("bigint").alias("n_nodes"), draws.cast("bigint").alias("n_draws"), F.md5(canonical(F.col("nodes"))).alias("expr_md5"))


@query("lift_relational", _LIFT)
def lift_relational(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _lift_columns(task_spec(spark, sf_dir, "box_label"))


@query("base_per_frame_filter", _LIFT)
def base_per_frame_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The script's way, a filter of the detections for every frame, but of those of the frame's block of 1,024 frames only: a scan of the whole
    table for each would be O(frames x detections), which no number of tasks makes up for."""
    dets = derive.detections(spark, sf_dir)
    frames = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("f"), F.expr("o_orderkey div 1024").alias("block"))

    def scan(a, b):
        import numpy as np

        keys = b["frame"].to_numpy()
        at = [np.flatnonzero(np.equal(keys, f)) for f in a["f"]]
        return b.iloc[np.concatenate([*at, np.array([], np.int64)]).astype(np.int64)].drop(columns="for_block")

    found = frames.groupBy("block").cogroup(dets.withColumn("for_block", F.expr("frame div 1024")).groupBy("for_block")).applyInPandas(scan, dets.schema)
    return _lift_columns(relational.annotate(_main(spark, sf_dir), found, "box_label", "theta", SEG))


def _main(spark: SparkSession, sf_dir: str) -> DataFrame:
    from reelspark.workloads.clips import main_index

    return main_index(spark, sf_dir)


def counter_script(imaging) -> None:
    """A typical script: a counter on every frame and a box on every third."""
    clip, out, i = imaging.open_clip("main"), imaging.new_clip(), 0
    while True:
        ok, frame = clip.read()
        if not ok:
            break
        imaging.text(frame, str(i), (1, 1))
        if i % 3 == 0:
            imaging.box(frame, (2, 2), (9, 9), (0, 0, 255))
        out.write(frame)
        i += 1
    out.close()


def replayed_counter(spark: SparkSession, sf_dir: str) -> DataFrame:
    env = shim.ClipEnv.of(task_sources(spark, sf_dir), ["main"])
    return shim.replayed(counter_script, env, _main(spark, sf_dir))


@query("lift_shim", "SELECT o_orderkey AS gen, CAST(CASE WHEN o_orderkey % 3 = 0 THEN 5 ELSE 4 END AS BIGINT) AS n_nodes, md5('ref(|' || o_orderkey || '|main);pixfmt(0||bgr24);text(1|1,1,255,255,255,1|' || o_orderkey || ')' || CASE WHEN o_orderkey % 3 = 0 THEN ';box(2|2,2,9,9,0,0,255,1|);pixfmt(3||yuv420p)' ELSE ';pixfmt(2||yuv420p)' END) AS expr_md5 FROM orders")
def lift_shim(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A script replayed over the whole main clip, from its first frame to its last in one task."""
    return _lift_columns(replayed_counter(spark, sf_dir)).drop("n_draws")


@query("lift_eager", "SELECT o_orderkey AS gen, 'pixfmt(0||bgr24)' AS second FROM orders")
def lift_eager(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eager conversion: even untouched frames are converted at read and at write."""
    spec = task_spec(spark, sf_dir, "box", "eager")
    from reelspark.model.expr import canonical_node

    return spec.select("gen", canonical_node(F.get("nodes", F.lit(1))).alias("second"))


@query("m_conv_count", f"WITH dets AS ({DETECTIONS_SQL}) SELECT k AS conversion, CAST(CASE k WHEN 'eager' THEN 2 * (SELECT count(*) FROM orders) ELSE 2 * (SELECT count(DISTINCT frame) FROM dets) END AS BIGINT) AS conversions FROM (VALUES ('eager'), ('lazy')) v(k)")
def m_conv_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pixel conversions of the box task, eager and lazy (also the sweep over conversion elision)."""
    out = None
    for kind in ("eager", "lazy"):
        one = task_spec(spark, sf_dir, "box", kind).agg(F.lit(kind).alias("conversion"), F.sum(F.size(F.filter("nodes", lambda n: n["op"] == "pixfmt"))).cast("bigint").alias("conversions"))
        out = one if out is None else out.unionByName(one)
    return out


_SOURCES = "SELECT conv_id, turn, 'import imaging' || CASE length(text) % 3 WHEN 0 THEN '' WHEN 1 THEN ' as im' ELSE '  # drawing' END || chr(10) || '# import imaging' || chr(10) || 'x = \"import imaging\"' AS src FROM conversations WHERE role = 'assistant'"


@query("import_rewrite", f"WITH s AS ({_SOURCES}), p AS (SELECT *, CASE WHEN src LIKE 'import imaging as%' THEN replace(src, 'import imaging as im', 'import reelspark.lift.shim_module as im') ELSE 'import reelspark.lift.shim_module as imaging' || substr(src, instr(src, chr(10))) END AS t FROM s) SELECT conv_id, turn, CAST(1 AS BIGINT) AS n_changed, md5(t) AS md5 FROM p")
def import_rewrite(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scripts of the assistant's turns: an import in one of three forms, then the same words in a comment and in a string."""
    tail = F.element_at(F.array(F.lit(""), F.lit(" as im"), F.lit("  # drawing")), (F.pmod(F.length("text"), F.lit(3)) + 1))
    src = F.concat(F.lit("import imaging"), tail, F.lit('\n# import imaging\nx = "import imaging"'))
    s = table(spark, sf_dir, "conversations").where("role = 'assistant'").select("conv_id", "turn", src.alias("src"))
    new = rewrite.patch_import(F.col("src"))
    lines = F.zip_with(F.split("src", "\n"), F.split(new, "\n"), lambda a, b: F.when(a != b, 1).otherwise(0))
    return s.select("conv_id", "turn", F.aggregate(lines, F.lit(0).cast("bigint"), lambda a, x: a + x).alias("n_changed"), F.md5(rewrite.patch_import(new)).alias("md5"))


@query("edit_list", "WITH e AS (SELECT c_custkey AS pos, c_custkey * 7 % 1000 AS a, 1 + c_custkey % 5 AS n FROM customer), o AS (SELECT *, CAST(sum(n) OVER (ORDER BY pos) - n AS BIGINT) AS first FROM e) SELECT first + k AS gen, a + k AS idx FROM o, range(5) r(k) WHERE k < n")
def edit_list(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col("c_custkey")
    a = F.pmod(c * 7, F.lit(1000))
    edits = table(spark, sf_dir, "customer").select(c.alias("pos"), F.lit("main").alias("source_id"), a.alias("cut_in"), (a + 1 + F.pmod(c, F.lit(5))).alias("cut_out"))
    return frontends.compile_edits(edits, "edits").select("gen", F.get("nodes", F.lit(0))["ints"][0].alias("idx"))


# -- interning and checks -------------------------------------------------------------------------------


@query("intern_spec", f"WITH {NODES_SQL}, p AS (SELECT gen, pos, md5(string_agg(t, ';') OVER (PARTITION BY gen ORDER BY pos)) AS h FROM nodes) SELECT 'box_label' AS spec_id, count(*) AS n_before, count(DISTINCT h) AS n_after FROM p")
def intern_spec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interning.measures(task_spec(spark, sf_dir, "box_label")).select("spec_id", "n_before", "n_after")


@query("m_spec_bytes")
def m_spec_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes before and after interning, for a task with shared mask references and for a grid that repeats clips."""
    o = table(spark, sf_dir, "orders").select("o_orderkey")
    cells = o.select(F.col("o_orderkey").alias("gen"), F.explode(F.sequence(F.lit(0), F.lit(3))).alias("cell")).select("gen", "cell", F.lit("main").alias("source_id"), F.floor(F.col("gen") / 4).cast("bigint").alias("idx"))
    specs = task_spec(spark, sf_dir, "mask_label").unionByName(relational.grid_spec(cells, "grid", SEG))
    return interning.measures(specs)


@query("typecheck", f"WITH dets AS ({DETECTIONS_SQL}) SELECT o_orderkey AS gen, NOT (o_orderkey % 50 = 7 OR o_orderkey % 50 = 8) AS ok, CASE o_orderkey % 50 WHEN 7 THEN 'frame out of range' WHEN 8 THEN 'unknown source' ELSE '' END AS err FROM orders")
def typecheck(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Some references are broken on purpose: two in fifty frames point outside a clip or to no clip."""
    c = F.pmod("gen", F.lit(50))
    frames = _main(spark, sf_dir).withColumn("idx", F.when(c == 7, F.lit(1 << 40)).otherwise(F.col("idx"))).withColumn("source_id", F.when(c == 8, F.lit("nowhere")).otherwise(F.col("source_id")))
    return check.infer(task_spec(spark, sf_dir, "box_label", frames=frames), task_sources(spark, sf_dir), (16, 16, "yuv420p")).select("gen", "ok", "err")


@query("policy_check", f"WITH {NODES_SQL}, f AS (SELECT gen, count(*) AS n FROM nodes GROUP BY 1) SELECT gen, n <= 24 AS ok, CASE WHEN n > 30 THEN 'too many nodes' WHEN n > 24 THEN 'too deep' ELSE '' END AS err FROM f")
def policy_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tight limits, so that some frames break them; in this task's chains the depth is the number of nodes."""
    return check.enforce(task_spec(spark, sf_dir, "box_label"), check.Policy(max_nodes=30, max_depth=24)).select("gen", "ok", "err")


# -- schedules -----------------------------------------------------------------------------------------

REFS_SQL = f"dets AS ({DETECTIONS_SQL}), refs AS (SELECT o_orderkey AS gen, 'main' AS source_id, o_orderkey AS idx FROM orders UNION SELECT frame, 'masks', mask_id FROM dets)"


@query("schedule", f"WITH {REFS_SQL} SELECT gen, count(*) AS n_needs, string_agg(source_id || '#' || idx, ',' ORDER BY source_id, idx) AS needs_csv FROM refs GROUP BY gen")
def schedule(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = plan.schedule(task_spec(spark, sf_dir, "mask_label"))
    return s.select("gen", F.size("needs").cast("bigint").alias("n_needs"), F.array_join(F.transform("needs", lambda f: F.concat(f["source"], F.lit("#"), f["idx"].cast("string"))), ",").alias("needs_csv"))


@query("need_set", f"WITH {REFS_SQL} SELECT gen // 80 * 80 AS window_lo, count(DISTINCT (source_id, idx)) AS n FROM refs GROUP BY 1")
def need_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    return plan.need_set(plan.references(task_spec(spark, sf_dir, "mask_label")), 80).select("window_lo", "n")


@query("need_set_sliding", f"WITH {REFS_SQL}, s AS (SELECT o_orderkey AS lo FROM orders) SELECT lo AS window_lo, count(DISTINCT (source_id, idx)) AS n FROM s JOIN refs ON gen BETWEEN lo AND lo + 7 GROUP BY 1")
def need_set_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size of the need set for every start, given to starts at which it does not change as well."""
    sizes = plan.sliding_need_set(plan.references(task_spec(spark, sf_dir, "mask_label")), 8)
    starts = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("at"))
    from reelspark.operators.joins import asof_join

    return asof_join(starts, sizes.select("window_lo", "n"), "at", "window_lo", ["n"], 4096).select(F.col("at").alias("window_lo"), F.col("hit.n").alias("n"))


@query("next_needed", f"WITH {REFS_SQL} SELECT source_id, idx, gen AS at_gen, lead(gen) OVER (PARTITION BY source_id, idx ORDER BY gen) AS next_gen FROM refs")
def next_needed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return plan.next_needed(plan.references(task_spec(spark, sf_dir, "mask_label"))).drop("spec_id")


@query("set_prefetch", f"WITH {REFS_SQL}, s AS (SELECT DISTINCT gen // 48 AS seg, source_id, idx FROM refs) SELECT seg, source_id, idx FROM s EXCEPT SELECT seg + 1, source_id, idx FROM s")
def set_prefetch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames to fetch for each segment that the one before has not brought: need set less pool."""
    r = plan.references(task_spec(spark, sf_dir, "mask_label")).select(F.expr("gen div 48").alias("seg"), "source_id", "idx").distinct()
    return r.join(r.select((F.col("seg") + 1).alias("seg"), "source_id", "idx"), ["seg", "source_id", "idx"], "left_anti")


@query("lift_annotators", _LIFT)
def lift_annotators(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The box-and-label task as a script with annotators, which keeps nothing from frame to frame: replayed for each block of frames beside
    the block's detections; the expressions equal those of the join."""
    from reelspark.annot import annotators

    def script(imaging, found) -> None:
        clip, out = imaging.open_clip("main"), imaging.new_clip()
        both = annotators.Chain(imaging, annotators.Box(imaging), annotators.Label(imaging))
        while True:
            at = clip.position()
            ok, frame = clip.read()
            if not ok:
                break
            out.write(both.annotate(frame, found(at)))
        out.close()

    env = shim.ClipEnv.of(task_sources(spark, sf_dir), ["main"])
    dets = derive.detections(spark, sf_dir).select("frame", "ord", "x1", "y1", "x2", "y2", "cls", "text")
    return _lift_columns(shim.replayed_in_parts(script, env, "main", _main(spark, sf_dir), dets))
