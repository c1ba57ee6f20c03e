"""Forms that work on many segments or frames at once give what the plain ones give."""

from dataclasses import asdict

import pytest
from pyspark.sql import functions as F

from reelspark import registry
from reelspark.engine import exec as engine
from reelspark.engine.core import Engine, EngineConfig, _planned, plan
from reelspark.sources.derive import GOP_LEN
from reelspark.workloads import clips

registry.load()


def test_counters_are_those_of_rendering(spark, sf_dir):
    """Every segment's counters, without pixels, are those of the run that renders it; and pixels stay in the store."""
    spec, gops, sources = clips.task_spec(spark, sf_dir, "box_label"), clips.task_gops(spark, sf_dir, "box_label"), clips.task_sources(spark, sf_dir)
    stats = engine.segment_stats(spec, gops, sources, GOP_LEN)
    plan = stats._jdf.queryExecution().executedPlan().toString()
    assert "packets" in plan and "bytes:binary" not in plan
    got = {r["seg"]: r.asDict() for r in stats.collect()}
    packed = [r.asDict(True) for r in engine._packed(gops, sources).collect()]
    by_seg: dict[int, list] = {}
    for r in spec.collect():
        by_seg.setdefault(r["seg"], []).append(r.asDict(True))
    assert set(got) == set(by_seg)
    for seg, rows in by_seg.items():
        touched = {r["nodes"][0]["ints"][0] // GOP_LEN for r in rows}
        _, want = engine.run_segment(rows, [g for g in packed if g["gop_id"] in touched], EngineConfig())
        assert {k: got[seg][k] for k in want if k in got[seg]} == {k: v for k, v in want.items() if k in got[seg]}


def test_a_plan_serves_every_schedule_of_its_shape():
    config, gop = EngineConfig(pool=20, window=16, decoders=2), 60
    _planned.cache_clear()
    for lo in (0, 60, 6000):
        schedule = [[("main", lo + (k * 7) % 90)] for k in range(48)]
        args = schedule, lambda f: ("main", f[1] // gop), lambda g: [("main", g[1] * gop + k) for k in range(gop)]
        got, frames, gops = plan(*args, config)
        assert got.stats == asdict(Engine(*args, config).run())
        assert gops == [("main", lo // gop), ("main", lo // gop + 1)] and frames[0] == ("main", lo // gop * gop)
    assert _planned.cache_info().misses == 1


@pytest.mark.parametrize("recipe", ["box_label", "mask_label"])
def test_needs_told_are_those_of_the_expressions(spark, sf_dir, recipe):
    from reelspark.plans.schedule import schedule

    told = schedule(clips.task_spec(spark, sf_dir, recipe, needed=True))
    assert "named_struct(op" not in told._jdf.queryExecution().optimizedPlan().toString()
    assert sorted(map(str, told.collect())) == sorted(map(str, schedule(clips.task_spec(spark, sf_dir, recipe)).collect()))


RECIPES = ["label", "box_label", "corner_label", "color_label", "mask_label"]


@pytest.mark.parametrize("recipe", RECIPES)
@pytest.mark.parametrize("conversion", ["lazy", "eager"])
def test_many_generations_evaluate_as_one_does(spark, sf_dir, recipe, conversion):
    import random

    from reelspark.engine import kernels

    table = clips.task_spec(spark, sf_dir, recipe, conversion).orderBy("gen").limit(400).toArrow()
    forest, nodes, rng = kernels.Forest(table.column("nodes")), table.column("nodes").to_pylist(), random.Random(1)
    frames: dict = {}

    def fetch(row, source, idx):
        w, h, fmt, n = (8, 8, "gray8", 64) if source == "masks" else (15, 17, "yuv420p", 255 + 2 * 72)
        return frames.setdefault((source, idx), (rng.randbytes(n), w, h, fmt))

    rows = list(range(len(nodes)))
    got = kernels.evaluate_many(forest, rows, fetch)
    for r in rows:
        assert forest.needs()[r] == engine._needs(nodes[r]) if r < 3 else True
        one = kernels.evaluate(engine._tuples(nodes[r]), lambda s, i, r=r: kernels.from_raw(*fetch(r, s, i)))
        assert got[r] == (*kernels.size_of(one), one[0], kernels.raw(one))
    assert kernels.digests([g[3] for g in got], 1000) == [kernels.digest((g[2], kernels.from_raw(g[3], *g[:3])[1])) for g in got]


def test_odd_drawings_evaluate_as_one_by_one():
    import pyarrow as pa

    from reelspark.engine import kernels

    node = lambda op, kids=(), ints=(), text="": {"op": op, "kids": list(kids), "ints": list(ints), "text": text}
    head = [node("ref", ints=[0], text="a"), node("pixfmt", [0], text="bgr24")]
    draws = [("text", [-5, -2, 1, 2, 3, 1], "Ab#?z"), ("text", [3, 4, 1, 2, 3, 2], "x1"), ("text", [40, 4, 1, 2, 3, 1], "x"), ("text", [0, 0, 9, 9, 9, 1], ""), ("box", [9, 9, 2, 2, 1, 2, 3, 1], ""), ("box", [-3, -3, 99, 5, 7, 8, 9, -1], ""), ("box", [2, 2, 9, 9, 7, 8, 9, 3], ""), ("corners", [0, 1, 12, 13, 5, 5, 5, 2], ""), ("tint", [1, 1, 99, 4, 255, 0, 7, 96], ""), ("line", [0, 0, 9, 3, 1, 2, 3], ""), ("flip", [1], ""), ("crop", [2, 2, 4, 4], ""), ("crop", [0, 0, 8, 6], "")]
    nodes = [[*head, node(op, [1], ints, text), node("pixfmt", [2], text="yuv420p")] for op, ints, text in draws]
    shape = pa.list_(pa.struct([("op", pa.string()), ("kids", pa.list_(pa.int32())), ("ints", pa.list_(pa.int64())), ("text", pa.string())]))
    data = bytes(range(256)) + bytes(range(128))
    got = kernels.evaluate_many(kernels.Forest(pa.array([[], *nodes], shape)[1:]), list(range(len(nodes))), lambda r, s, i: (data, 16, 16, "yuv420p"))
    for n, g in zip(nodes, got, strict=True):
        one = kernels.evaluate(engine._tuples(n), lambda s, i: kernels.from_raw(data, 16, 16, "yuv420p"))
        assert g == (*kernels.size_of(one), one[0], kernels.raw(one))


def test_segments_together_render_as_each_alone(spark, sf_dir):
    import pyarrow as pa

    config = EngineConfig(pool=20, window=16, decoders=3)
    spec = clips.task_spec(spark, sf_dir, "box_label").where("gen < 400").toArrow()
    gops = engine._packed(clips.task_gops(spark, sf_dir, "box_label", b_run=2), clips.task_sources(spark, sf_dir)).where("gop_id < 7").toArrow()
    got = engine.run_segments(spec, gops, config)
    alone = {}
    for seg in set(spec.column("seg").to_pylist()):
        rows, _ = engine.run_segment([r for r in spec.to_pylist() if r["seg"] == seg], gops.to_pylist(), config)
        alone |= {g: engine.kernels.raw(f) for g, f in rows}
    assert dict(zip(got.column("gen").to_pylist(), got.column("data").to_pylist(), strict=True)) == alone
    assert engine.run_segments(spec.slice(0, 0), gops, config).num_rows == 0 and isinstance(got, pa.Table)


def test_boxes_by_slices_are_those_of_the_mask():
    import itertools

    import numpy as np

    from reelspark.engine import kernels

    img = np.random.default_rng(0).integers(0, 256, (7, 6, 3), dtype=np.uint8)
    for x1, x2, y1, y2, thick in itertools.product((-4, -1, 0, 3, 8), (-2, 0, 4, 9), (-3, 1, 9), (-1, 3, 8), (-1, 0, 1, 2, 5)):
        want = kernels.paint(img, kernels._edges(x1, y1, x2, y2, thick, None, 6, 7), (1, 2, 3))
        assert (kernels._boxed(img, x1, y1, x2, y2, thick, (1, 2, 3)) == want).all(), (x1, y1, x2, y2, thick)


def test_hue_styles_run_in_tasks(spark, sf_dir):
    """The order is no list on the driver, and every style's counters are those of the plain call."""
    from reelspark.baseline.hue import STYLES
    from reelspark.workloads import search

    df = registry.QUERIES["w_hue_scripts"](spark, sf_dir)
    assert "MapInArrow" in df._jdf.queryExecution().executedPlan().toString()
    order = [r["vec_id"] for r in search.w_hue(spark, sf_dir).orderBy("pos").collect()]
    want = {(s, g): f(order, g) for s, f in STYLES.items() for g in (60, 250)}
    assert {(r["style"], r["gop_len"]): {c: r[c] for c in ("frames_decoded", "peak_resident")} for r in df.collect()} == want


def test_urgencies_are_asked_for_only_to_give_up_a_decoder():
    import random

    calls = [0]

    class Counted(Engine):
        def urgency(self, d):
            calls[0] += 1
            return super().urgency(d)

    order = random.Random(1).sample(range(300), 300)
    stats = Counted([[i] for i in order], lambda f: f // 60, lambda g: list(range(g * 60, g * 60 + 60)), EngineConfig(pool=100, window=80, decoders=1)).run()
    assert stats.frames_decoded >= 300 and calls[0] < stats.ticks / 2


def test_drawings_by_slices_are_those_of_the_mask():
    """Corners, tints and texts touch their own pixels only, in colour and in grey."""
    import itertools

    import numpy as np

    from reelspark.engine import kernels
    from reelspark.engine.font import text_mask

    rng = np.random.default_rng(0)
    for img in (rng.integers(0, 256, (7, 6, 3), dtype=np.uint8), rng.integers(0, 256, (7, 6), dtype=np.uint8)):
        c = (1, 2, 3) if img.ndim == 3 else (9,)
        for x1, x2, y1, y2, reach in itertools.product((-4, 0, 3, 8), (-2, 0, 4, 9), (-3, 1, 9), (-1, 3, 8), (0, 1, 3, 9)):
            want = kernels.paint(img, kernels._edges(x1, y1, x2, y2, 1, reach, 6, 7), c)
            assert (kernels._cornered(img, x1, y1, x2, y2, reach, c) == want).all(), (x1, y1, x2, y2, reach)
            want = kernels.blend(img, kernels._edges(x1, y1, x2, y2, -1, None, 6, 7), c, 96)
            assert (kernels._tinted(img, x1, y1, x2, y2, c, 96) == want).all(), (x1, y1, x2, y2)
        for text, x, y, scale in itertools.product(("", "a", "Ab#?z"), (-7, -1, 0, 5, 6), (-6, -1, 0, 3, 7), (1, 2, 3)):
            assert (kernels._lettered(img, text, x, y, scale, c) == kernels.paint(img, text_mask(text, x, y, scale, 6, 7), c)).all(), (text, x, y, scale)


def test_conversions_of_even_and_odd_frames_agree():
    """Even frames take a way of their own; padded by their edge, odd ones must give the same bytes."""
    import numpy as np

    from reelspark.engine import kernels

    rng = np.random.default_rng(0)
    for h, w in ((16, 16), (2, 4), (8, 6)):
        planes = [rng.integers(0, 256, s, dtype=np.uint8) for s in ((h, w), (h // 2, w // 2), (h // 2, w // 2))]
        assert (kernels.yuv_to_bgr(planes)[:-1, :-1] == kernels.yuv_to_bgr([planes[0][:-1, :-1], *planes[1:]])).all()
        one = np.moveaxis(kernels._many_bgr([p[None] for p in planes])[0], 0, -1)
        assert (kernels.yuv_to_bgr(planes) == one).all()
        assert all((a == b[0]).all() for a, b in zip(kernels.bgr_to_yuv(one), kernels._many_yuv(np.moveaxis(one, -1, 0)[None]), strict=True))


@pytest.mark.parametrize("recipe", ["box_label", "mask_label"])
def test_a_divided_script_writes_what_one_task_does(spark, sf_dir, recipe):
    from reelspark.baseline import script
    from reelspark.sources import derive

    gops, dets = clips.task_gops(spark, sf_dir, recipe), derive.detections(spark, sf_dir)
    one, many = (script.render(gops, dets, recipe, alone=alone) for alone in (True, False))
    assert many.rdd.getNumPartitions() > one.rdd.getNumPartitions() == 1
    assert sorted(map(tuple, many.collect())) == sorted(map(tuple, one.collect()))


def test_the_script_is_clocked_in_parts(spark, sf_dir):
    """All frames count, and the seconds are those of the parts one after another."""
    from reelspark.baseline import script
    from reelspark.sources import derive

    gops, dets = clips.task_gops(spark, sf_dir, "box_label"), derive.detections(spark, sf_dir)
    n, seconds = script.seconds(gops, dets, "box_label")
    assert n == clips.main_index(spark, sf_dir).count() and seconds > 0
    assert script.seconds(gops.where("false"), dets, "box_label")[0] == 0


def test_exchange_copies_no_frame_to_each_generation(spark, sf_dir):
    """A block's frames meet its expressions once; blocks of any size render as segments do."""
    spec, gops, sources = clips.task_spec(spark, sf_dir, "mask_label", needed=True), clips.task_gops(spark, sf_dir, "mask_label"), clips.task_sources(spark, sf_dir)
    frames = lambda df: sorted((r["gen"], bytes(r["data"])) for r in df.collect())
    want = frames(engine.segment_local(spec, gops, sources, GOP_LEN))
    for block in (None, 1, 100):
        df = engine.gop_exchange(spec, gops, sources, GOP_LEN, block)
        assert "FlatMapCoGroupsInArrow" in df._jdf.queryExecution().executedPlan().toString()
        assert frames(df) == want


def test_stored_lists_hold_every_detection(spark, sf_dir):
    from reelspark.sources import derive

    told, made = (clips.task_spec(spark, sf_dir, "mask_label", "eager", needed=True, stored=stored) for stored in (True, False))
    assert "lineitem" not in told._jdf.queryExecution().optimizedPlan().toString()
    assert sorted(map(str, told.collect())) == sorted(map(str, made.collect()))
    dets = clips.stored_detections(spark, sf_dir)
    made = derive.detections(spark, sf_dir).join(clips.main_index(spark, sf_dir).select("gen"), F.col("frame") == F.col("gen"), "left_semi")
    assert sorted(map(str, dets.select(sorted(dets.columns)).collect())) == sorted(map(str, made.select(sorted(dets.columns)).collect()))


def test_exactness_meets_in_one_grouping(spark, sf_dir):
    """Every task's scripts and renders meet in one grouping; detections are not made anew for each, and the script is no lone task."""
    plan = registry.QUERIES["m_exact"](spark, sf_dir)._jdf.queryExecution().optimizedPlan().toString()
    assert "FullOuter" not in plan and "l_orderkey" not in plan and "Repartition 1," not in plan


def test_settings_read_the_listed_detections(spark, sf_dir):
    assert "l_orderkey" not in registry.QUERIES["m_exact_settings"](spark, sf_dir)._jdf.queryExecution().optimizedPlan().toString()


def test_the_script_query_is_no_lone_task(spark, sf_dir):
    df = registry.QUERIES["base_script"](spark, sf_dir)
    assert "Repartition 1," not in df._jdf.queryExecution().optimizedPlan().toString()
    got = sorted(map(tuple, df.collect()))
    assert [g for g, _ in got] == sorted(r["gen"] for r in clips.main_index(spark, sf_dir).collect())


def test_mixed_colours_are_those_of_wide_arithmetic():
    """Colours beyond a byte and shares beyond one keep their results."""
    import itertools

    import numpy as np

    from reelspark.engine import kernels

    for img in (np.arange(256, dtype=np.uint8).reshape(8, 32), np.arange(192, dtype=np.uint8).reshape(8, 8, 3)):
        for color, alpha in itertools.product(((0, 7, 255), (-3, 300, 9)), (-5, 0, 96, 256, 300)):
            want = ((256 - alpha) * img.astype(np.int64) + alpha * np.array(color if img.ndim == 3 else color[0])) >> 8
            assert (kernels._mixed(img, color, alpha).astype(np.uint8) == want.astype(np.uint8)).all(), (color, alpha)


def test_drawings_that_wait_are_those_painted_at_once():
    import random

    import numpy as np

    from reelspark.engine import kernels

    rng, colors = random.Random(3), [(0, 0, 255), (1, 2, 3), (255, 255, 255)]
    for h, w in ((7, 6), (16, 16), (5, 70), (1, 1)):
        plain = "bgr24", [np.random.default_rng(h).integers(0, 256, (h, w, 3), dtype=np.uint8)]
        for _ in range(60):
            one, many = plain, kernels.canvas(plain)
            for _ in range(rng.randint(0, 9)):
                box, c = [rng.randint(-4, w + 3), rng.randint(-4, h + 3), rng.randint(-4, w + 9), rng.randint(-4, h + 9)], rng.choice(colors)
                many = kernels.canvas(kernels.painted(many)) if rng.random() < 0.2 else many
                op, ints, text = rng.choice([("box", [*box, *c, rng.randint(-1, 4)], ""), ("corners", [*box, *c, rng.randint(0, 4)], ""), ("text", [*box[:2], *c, rng.randint(1, 2)], rng.choice(["", "a", "Ab#?z"])), ("tint", [*box, *c, 96], "")])
                one, many = (kernels.apply_node(op, [f], ints, text) for f in (one, many))
            assert (kernels.painted(many)[1][0] == one[1][0]).all()


def test_lifting_copies_no_node_for_its_type(spark, sf_dir):
    for recipe in RECIPES:
        assert "as struct<op" not in clips.task_spec(spark, sf_dir, recipe)._jdf.queryExecution().optimizedPlan().toString()


def test_gops_decoded_at_once_are_those_decoded_one_by_one(monkeypatch):
    import random

    from reelspark.sources import codec

    rng = random.Random(5)
    for n, b_run, intra, size in ((1, 0, False, 9), (60, 0, False, 384), (61, 2, False, 64), (7, 3, False, 5), (12, 0, True, 16)):
        packets = codec.encode([rng.randbytes(size) for _ in range(n)], b_run, intra, 100)
        pairs = [(p["kind"], p["bytes"]) for p in packets]
        want = [raw for _, raw in codec.decode(packets)]
        for chunk in (1, 3 * size, 1 << 16):
            monkeypatch.setattr(codec, "CHUNK", chunk)
            assert codec.decoded(pairs) == want
            assert [list(codec.first_frames(pairs, k)) for k in (0, 1, n)] == [[], want[:1], want]


def test_many_small_pictures_are_drawn_on_as_one_is():
    """Drawings of many generations that wait together, by few colours and by many, give what each drawing alone gives."""
    import random

    import numpy as np

    from reelspark.engine import kernels

    rng, n, texts = random.Random(7), 9, ["", "a", "Ab#?z", "large ring"]
    for h, w, colors in ((16, 16, 3), (7, 6, 3), (5, 40, 3), (4, 64, 3), (16, 16, 40), (3, 70, 3)):
        palette = [[rng.randrange(256) for _ in range(3)] for _ in range(colors)]
        img = np.random.default_rng(h).integers(0, 256, (n, 3, h, w), dtype=np.uint8)
        many, ones = ("bgr24", [img]), [kernels.single(("bgr24", [img]), i) for i in range(n)]
        for _ in range(12):
            op = rng.choice(["box", "corners", "text", "tint"])
            place = lambda: [rng.randint(-4, w + 3), rng.randint(-4, h + 3)]  # noqa: B023, E731
            last = {"box": lambda: rng.randint(-1, 4), "corners": lambda: rng.randint(0, 4), "tint": lambda: 96}.get(op)
            ints = np.array([[*place(), *rng.choice(palette), 1] if op == "text" else [*place(), *place(), *rng.choice(palette), last()] for _ in range(n)], np.int64)
            codes = np.array([rng.randrange(len(texts)) for _ in range(n)])
            many = kernels._apply_many(op, [many], ints, texts, codes)
            ones = [kernels.apply_node(op, [f], ints[i].tolist(), texts[codes[i]]) for i, f in enumerate(ones)]
        many = kernels._flat(many)
        assert all((kernels.single(many, i)[1][0] == f[1][0]).all() for i, f in enumerate(ones)), (h, w, colors)
