"""Headline timings: prints one JSON line. BENCH_SF_DIR (default sf0.1) and BENCH_CPUS choose data and threads."""

from __future__ import annotations

import json
import os
import re
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ.setdefault("PYTHONPATH", os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from reelspark.session import session

    spark = session(CPUS, max(8, int(CPUS) if CPUS.isdigit() else 8), "12g")
    spark.range(1000).selectExpr("sum(id)").collect()

    from reelspark import registry
    from reelspark.baseline import script
    from reelspark.engine import exec as engine
    from reelspark.sources import derive
    from reelspark.sources.derive import GOP_LEN
    from reelspark.vod.service import first_segment_seconds
    from reelspark.workloads import clips

    registry.load()
    seconds: dict[str, float] = {}
    frames: dict[str, int] = {}

    def clock(name: str, make) -> None:
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)

    place = tempfile.mkdtemp(prefix="reelbench-")
    began = time.perf_counter()
    clips.task_gops(spark, SF_DIR, "mask_label").write.parquet(f"{place}/gops")
    seconds["ingest"] = round(time.perf_counter() - began, 3)
    gops, sources = spark.read.parquet(f"{place}/gops"), clips.task_sources(spark, SF_DIR).cache()
    n = sources.where("source_id = 'main'").first()["n_frames"]
    specs = {}
    for task, recipe in clips.TASKS.items():
        began = time.perf_counter()
        clips.task_spec(spark, SF_DIR, recipe).repartition("seg").write.partitionBy("spec_id").parquet(f"{place}/{task}")
        seconds[f"lift_{task[2:]}"] = round(time.perf_counter() - began, 3)
        specs[task] = spark.read.parquet(f"{place}/{task}")
        plan = "gop_exchange" if "mask" in recipe else "segment_local"
        clock(f"engine_{task[2:]}", lambda task=task, plan=plan: engine.render(specs[task], gops, sources, GOP_LEN, plan=plan))
        first_segment_seconds(specs[task], gops, sources)
        seconds[f"first_segment_{task[2:]}"] = round(first_segment_seconds(specs[task], gops, sources), 3)
    dets = derive.detections(spark, SF_DIR).cache()
    dets.count()
    clock("script_box_label", lambda: script.render(gops.where("source_id = 'main'"), dets, "box_label"))
    frames["engine"] = n
    entry = __import__("__spark_entry__").queries()
    for name in ("lift_relational", "w_search", "w_hue", "join_asof", "agg_cube", "manifest_event", "op2_simhash", "op8_quality_rules", "op9_block_search", "op10_toxicity"):
        if name in entry:
            clock(name, lambda name=name: entry[name](spark, SF_DIR))
    sizes = {f"{r['w']}x{r['h']}": [r["frames_per_second"], r["megapixels_per_second"], r["process_mb"]] for r in registry.QUERIES["m_frame_size"](spark, SF_DIR).collect()}
    total = round(sum(v for k, v in seconds.items() if k.startswith("engine_")), 3)
    rates = {k: round(n / v, 1) for k, v in seconds.items() if k.startswith(("engine_", "script_"))}
    print(json.dumps({"metric": "five annotation tasks, full render", "value": total, "unit": "sec", "queries": seconds, "frames": n, "frames_per_second": rates, "speedup_box_label": round(seconds["script_box_label"] / seconds["engine_box_label"], 2), "on_demand_box_label": round(seconds["script_box_label"] / seconds["first_segment_box_label"], 1), "frame_sizes_fps_mpx_mb": sizes, "cpus": CPUS, "sf": (re.search(r"sf([0-9.]+)", SF_DIR) or [None, None])[1]}))


if __name__ == "__main__":
    main()
