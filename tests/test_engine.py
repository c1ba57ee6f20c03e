"""The scheduler: worked cases, invariants, small-state exploration, eviction, codec and kernels."""

import itertools
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from reelspark.engine import kernels, kernels_scalar
from reelspark.engine.core import Engine, EngineConfig, EngineStuck, PoolTooSmall, fewest_misses, least_decodes, seek_decodes, simulate
from reelspark.engine.font import text_extent, text_mask
from reelspark.sources import codec


def test_decode_order_of_a_gop_of_three():
    assert [p["idx"] + 1 for p in codec.encode([b"a", b"b", b"c"], b_run=1)] == [1, 3, 2]


@pytest.mark.parametrize("b_run", [0, 1, 2])
@pytest.mark.parametrize("n", [1, 2, 3, 7, 30])
def test_codec_round_trip(n, b_run):
    rng = random.Random(n)
    frames = [rng.randbytes(24) for _ in range(n)]
    packets = codec.encode(frames, b_run, first=9)
    assert dict(codec.decode(packets)) == {9 + i: f for i, f in enumerate(frames)}
    assert dict(codec.decode(codec.encode(frames, all_intra=True))) == dict(enumerate(frames))
    assert [i for i, _ in codec.decode(packets, 0)] == [9]


def test_regression_decoder_with_pooled_future_is_released():
    s = simulate([[0, 3, 5, 6], [0, 1, 5, 6], [1, 3, 5, 7], [0, 4, 6]], 3, 8, EngineConfig(pool=4, decoders=1))
    assert s["peak_pool"] <= 4


def test_pool_too_small_is_told_before_any_decode():
    with pytest.raises(PoolTooSmall) as e:
        simulate([[0], [1, 2, 3]], 2, 8, EngineConfig(pool=2))
    assert (e.value.gen, e.value.need, e.value.pool) == (1, 3, 2)


def test_empty_schedule_and_generation_without_inputs():
    assert simulate([], 4, 0)["frames_decoded"] == 0
    assert simulate([[], [0], []], 4, 4)["frames_decoded"] == 1


def test_without_abandonment_scattered_access_can_deadlock():
    import hashlib

    s = sorted([[i] for i in range(500)], key=lambda x: hashlib.md5(f"7:{x[0]}".encode()).hexdigest())
    with pytest.raises(EngineStuck):
        simulate(s, 60, 500, EngineConfig(pool=30, window=24, decoders=2, abandon=False))


def checked(schedule, gop, n, cfg, b_run=0):
    """Runs with every invariant checked at every tick; returns the outputs in order and the counters."""
    orders = {g: [g * gop + k for k, *_ in codec.decode_order(min(gop, n - g * gop), b_run)] for g in range(-(-n // gop))}
    out, rendered = [], []

    def render(g, have):
        assert set(have) == set(schedule[g])  # a generation renders only with all its inputs
        rendered.append(g)
        return tuple(sorted(have.values()))

    e = Engine(schedule, lambda f: f // gop, orders.__getitem__, cfg, lambda g: iter([f * 10 for f in orders[g]]), render, lambda g, x: out.append((g, x)))
    idle = 0
    while not e.finished():
        idle = 0 if e.tick() else idle + 1
        assert idle < 2, "no progress"
        assert len(e.need) <= cfg.pool and len(e.pool) <= cfg.pool
        assert e.stats.ticks < 100_000
    assert out == [(g, tuple(sorted(f * 10 for f in set(s)))) for g, s in enumerate(schedule)]
    if b_run == 0:
        assert e.stats.frames_decoded >= least_decodes(schedule, gop) or cfg.emit == "display"
    return e.stats


cases = st.integers(1, 4).flatmap(lambda gop: st.integers(1, 10).flatmap(lambda n: st.integers(1, 5).flatmap(lambda pool: st.tuples(st.just(gop), st.just(n), st.just(pool), st.lists(st.lists(st.integers(0, n - 1), max_size=pool, unique=True), max_size=6)))))


@settings(max_examples=400, deadline=None)
@given(cases, st.integers(1, 6), st.integers(1, 3), st.integers(1, 3), st.sampled_from(["next_needed", "lru", "fifo", "random"]), st.sampled_from(["encode", "render"]), st.sampled_from(["decode", "display"]), st.integers(0, 2))
def test_invariants(case, window, decoders, filters, evict, release, emit, b_run):
    gop, n, pool, schedule = case
    checked(schedule, gop, n, EngineConfig(pool=pool, window=window, decoders=decoders, filters=filters, evict=evict, release=release, emit=emit), b_run)


def test_every_small_state():
    """All schedules of up to three generations over two GOPs of three frames, for all small settings and two phase orders."""
    sets = [c for k in (1, 2) for c in itertools.combinations(range(6), k)]
    for schedule in itertools.product(sets[::3], repeat=3):
        for pool, decoders in ((2, 1), (2, 2), (3, 1), (4, 2)):
            for phases in (("encode", "admit", "assign", "decode", "abandon", "filter"), ("filter", "abandon", "decode", "assign", "admit", "encode")):
                checked([list(s) for s in schedule], 3, 6, EngineConfig(pool=pool, window=2, decoders=decoders, filters=1, phases=phases))


def test_reverse_needs_no_more_than_the_least_once_a_gop_fits():
    reverse = [[i] for i in range(500)][::-1]
    decoded = [simulate(reverse, 60, 500, EngineConfig(pool=p, window=p * 8 // 10, decoders=4, filters=4))["frames_decoded"] for p in (10, 30, 60, 100)]
    assert decoded == sorted(decoded, reverse=True) and decoded[2] == decoded[3] == 500
    assert seek_decodes(reverse, 60) == sum(i % 60 + 1 for i in range(500)) > decoded[0]


def test_wide_strides_gain_from_decoders_in_proportion():
    s = [[k * 128] for k in range(200)]
    ticks = {d: simulate(s, 60, None, EngineConfig(decoders=d, filters=16))["ticks"] for d in (1, 16)}
    assert ticks[1] / ticks[16] > 10


def test_lookahead_is_no_worse_than_recency():
    rng = random.Random(3)
    s = [[i] for i in range(300)]
    rng.shuffle(s)
    runs = {e: simulate(s, 30, 300, EngineConfig(pool=40, window=32, decoders=2, evict=e))["frames_decoded"] for e in ("next_needed", "lru")}
    assert runs["next_needed"] <= runs["lru"]


def test_optimal_misses_on_a_small_trace():
    trace = [0, 1, 2, 0, 1, 3, 0, 3, 1, 2]

    def brute(i, cache):
        if i == len(trace):
            return 0
        if trace[i] in cache:
            return brute(i + 1, cache)
        room = [cache] if len(cache) < 2 else [cache - {x} for x in cache]
        return 1 + min(brute(i + 1, c | {trace[i]}) for c in room)

    assert fewest_misses(trace, 2) == brute(0, frozenset())


def test_kernels_agree_with_the_scalar_ones():
    rng = np.random.default_rng(1)
    for _ in range(60):
        f = ("yuv420p", [rng.integers(0, 256, (16, 16), dtype=np.uint8), *(rng.integers(0, 256, (8, 8), dtype=np.uint8) for _ in range(2))])
        nodes = [("ref", [], [0], "c"), ("pixfmt", [0], [], "bgr24")]
        for _ in range(rng.integers(1, 5)):
            x1, y1 = (int(v) for v in rng.integers(-3, 15, 2))
            x2, y2 = x1 + int(rng.integers(0, 9)), y1 + int(rng.integers(0, 9))
            c = [int(v) for v in rng.integers(0, 256, 3)]
            op, ints, text = [("box", [x1, y1, x2, y2, *c, int(rng.choice([-1, 1, 2]))], ""), ("corners", [x1, y1, x2, y2, *c, 2], ""), ("tint", [x1, y1, x2, y2, *c, 96], ""), ("text", [x1, y1, *c, int(rng.choice([1, 2]))], "a7:z")][rng.integers(0, 4)]
            nodes.append((op, [len(nodes) - 1], ints, text))
        nodes.append(("pixfmt", [len(nodes) - 1], [], "yuv420p"))
        assert kernels.raw(kernels.evaluate(nodes, lambda s, i, f=f: f)) == kernels.raw(kernels_scalar.evaluate(nodes, lambda s, i, f=f: f))


def test_drawing_needs_the_right_format():
    with pytest.raises(TypeError):
        kernels.apply_node("box", [("yuv420p", [np.zeros((4, 4), np.uint8)] * 3)], [0, 0, 1, 1, 0, 0, 0, 1], "")


def test_text_extent_covers_the_mask():
    w, h = text_extent("ab1", 2)
    mask = text_mask("ab1", 0, 0, 2, 64, 64)
    assert mask[:h, :w].sum() == mask.sum() and text_extent("") == (0, 0)


def test_raw_round_trip():
    for fmt, n in (("yuv420p", 96), ("bgr24", 192), ("gray8", 64)):
        data = bytes(range(n))
        assert kernels.raw(kernels.from_raw(data, 8, 8, fmt)) == data


@pytest.mark.parametrize(
    ("schedule", "gop", "n", "cfg"),
    [
        ([[3]] * 40, 4, 8, EngineConfig(pool=1, window=1, decoders=8)),  # one frame for all, more decoders than GOPs
        ([[0]], 1, 1, EngineConfig(pool=1, window=1, decoders=1, filters=1)),  # a clip of one frame
        ([[i] for i in range(96)], 60, 96, EngineConfig(pool=1, window=96)),  # last GOP short, pool of one
        ([[0, 0, 5, 5]], 3, 6, EngineConfig(pool=2)),  # a frame twice in one generation
        ([[i, 47 - i] for i in range(48)], 16, 48, EngineConfig(pool=6, window=3, decoders=2)),
    ],
)
def test_edge_cases(schedule, gop, n, cfg):
    stats = checked([sorted(set(s)) for s in schedule], gop, n, cfg)
    if len(set(map(tuple, schedule))) == 1:
        assert stats.gop_opens <= 2


def test_jitter_does_not_change_the_output():
    for seed in range(5):
        checked([[i, (i * 7) % 60] for i in range(60)], 12, 60, EngineConfig(pool=12, window=8, decoders=3, jitter=0.4, seed=seed), 2)


@pytest.mark.parametrize(("b_run", "all_intra"), [(0, False), (2, False), (0, True)])
def test_plans_agree_with_gaps_and_a_frame_for_all(spark, b_run, all_intra):
    """A clip with gaps, B packets, a short last GOP, and one frame that every generation uses (over several blocks)."""
    from pyspark.sql import functions as F

    from reelspark.engine import exec as engine
    from reelspark.model.expr import node, ref
    from reelspark.model.schemas import NODE
    from reelspark.sources import gopindex

    rng = random.Random(b_run)
    there = sorted(rng.sample(range(200), 120))
    frames = spark.createDataFrame([("clip", i, rng.randbytes(64)) for i in there] + [("logo", 3, rng.randbytes(64))], "source_id string, idx bigint, raw binary")
    gops = gopindex.encode(frames, 17, b_run, all_intra).cache()
    sources = spark.createDataFrame([("clip", 8, 8, "gray8"), ("logo", 8, 8, "gray8")], "source_id string, width int, height int, fmt string")
    gens = [(g, rng.choice(there)) for g in range(90)]
    index = spark.createDataFrame(gens, "gen bigint, idx bigint")
    spec = index.select(F.lit("s").alias("spec_id"), "gen", F.expr("gen div 20").alias("seg"), F.array(ref("clip", F.col("idx")), ref("logo", F.lit(3)), node("blend", [0, 1], [100])).cast(f"array<{NODE}>").alias("nodes"))
    raw = {(r["source_id"], r["idx"]): np.frombuffer(r["raw"], np.uint8).astype(int) for r in frames.collect()}
    before, engine.BLOCK = engine.BLOCK, 16
    try:
        out = {p: {r["gen"]: bytes(r["data"]) for r in engine.render(spec, gops, sources, None, EngineConfig(pool=7, window=5, decoders=2), p).collect()} for p in ("segment_local", "gop_exchange", "auto")}
    finally:
        engine.BLOCK = before
    assert out["segment_local"] == out["gop_exchange"] == out["auto"] and len(out["auto"]) == 90
    blended = {g: kernels.raw(kernels.apply_node("blend", [kernels.from_raw(raw["clip", i].astype(np.uint8).tobytes(), 8, 8, "gray8"), kernels.from_raw(raw["logo", 3].astype(np.uint8).tobytes(), 8, 8, "gray8")], [100], "")) for g, i in gens}
    assert out["auto"] == blended
    # the index tells decode positions, which arithmetic can't here
    at = {r["idx"]: r["dpos"] for r in gopindex.frame_index(gops).where("source_id = 'clip'").collect()}
    assert set(at) == set(there) and (b_run == 0 or any(at[i] != i % 17 for i in there))


def test_odd_sizes():
    rng = np.random.default_rng(3)
    for w, h in ((5, 7), (1, 1), (6, 5)):
        f = ("bgr24", [rng.integers(0, 256, (h, w, 3), dtype=np.uint8)])
        y = kernels.pixfmt(f, "yuv420p")
        assert [p.shape for p in y[1]] == [(h, w), (-(-h // 2), -(-w // 2)), (-(-h // 2), -(-w // 2))]
        assert kernels.pixfmt(y, "bgr24")[1][0].shape == (h, w, 3)
        assert kernels.raw(kernels.from_raw(kernels.raw(y), w, h, "yuv420p")) == kernels.raw(y)


def test_display_order_holds_little():
    for n, b_run in ((1, 0), (9, 2), (30, 1)):
        assert [i for i, _ in codec.in_display_order(codec.encode([bytes([k]) for k in range(n)], b_run))] == list(range(n))


def test_pixels_are_never_broadcast(spark, sf_dir):
    import re

    from reelspark.workloads.rendering import m_lossy_round_trip

    plan = m_lossy_round_trip(spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    for side in re.split(r"BroadcastExchange", plan)[1:]:
        assert not re.search(r"raw#|frames#", side.split("\n")[1])
    assert "SortMergeJoin [idx" in plan
