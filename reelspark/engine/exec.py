"""The engine on Spark: two decode plans over the same kernels.

segment_local: a task gets a segment's expressions and the compressed packets they touch, and runs the pool
scheduler inside; only compressed packets cross the network. gop_exchange: every touched GOP is decoded once, up
to its deepest needed packet, and pixels go to the generations that need them. The result is the same.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import asdict

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.engine import kernels
from reelspark.engine.core import Engine, EngineConfig, plan
from reelspark.model.schemas import NODE, STATS
from reelspark.operators.joins import sized_broadcast
from reelspark.plans.schedule import indexed, located, references, schedule
from reelspark.sources import codec, gopindex

OUT = "spec_id string, gen bigint, w int, h int, fmt string, data binary"
_OUT = pa.schema([("spec_id", pa.string()), ("gen", pa.int64()), ("w", pa.int32()), ("h", pa.int32()), ("fmt", pa.string()), ("data", pa.binary())])


def _tuples(nodes: list[dict]) -> list[tuple]:
    return [(n["op"], n["kids"], n["ints"], n["text"]) for n in nodes]


def _needs(nodes: list[dict]) -> list[tuple]:
    return [(n["text"], n["ints"][0]) for n in nodes if n["op"] == "ref"]


def run_segment(spec: list[dict], gops: list[dict], config: EngineConfig) -> tuple[list[tuple], dict]:
    """Renders the generations of a segment from its packets: rows (gen, frame) and counters."""
    spec = sorted(spec, key=lambda r: r["gen"])
    by_gop = {(g["source_id"], g["gop_id"]): g for g in gops}
    gop_of = {(g["source_id"], p["idx"]): (g["source_id"], g["gop_id"]) for g in gops for p in g["packets"]}
    shape = {g["source_id"]: (g["width"], g["height"], g["fmt"]) for g in gops}
    trees, rows = [_tuples(r["nodes"]) for r in spec], []

    def packets(gop):
        return [(gop[0], p["idx"]) for p in by_gop[gop]["packets"]]

    def open_gop(gop):
        return (kernels.from_raw(data, *shape[gop[0]]) for _, data in codec.decode(by_gop[gop]["packets"]))

    engine = Engine([_needs(r["nodes"]) for r in spec], gop_of.__getitem__, packets, config, open_gop, lambda g, have: kernels.evaluate(trees[g], lambda s, i: have[s, i]), lambda g, out: rows.append((spec[g]["gen"], out)))
    stats = engine.run()
    return rows, asdict(stats)


def _packed(gops: DataFrame, sources: DataFrame) -> DataFrame:
    return gops.join(sized_broadcast(sources.select("source_id", "width", "height", "fmt")), "source_id")


#: Segments that travel together; each is scheduled by itself. More of them are fewer and longer arrays.
TOGETHER = 64

#: Generations whose copies of one frame travel together: a frame that all generations use is many rows, none of them hot.
BLOCK = 2048


def _touched(spec: DataFrame, gops: DataFrame, gop_len: int | None) -> DataFrame:
    """References with GOP and decode position: by arithmetic where all GOPs have ``gop_len`` frames, I and P; else (None) by the index."""
    return located(references(spec), gop_len) if gop_len else indexed(references(spec), gops)


#: Bytes of inputs that wait to be rendered together, beside the pool.
WAITING = 1 << 22


def _given(gops: pa.Table) -> list[tuple]:
    """(source, GOP, (width, height, format), indices, [(kind, bytes)]) of each row."""
    out = []
    for b in gops.to_batches():
        source, gop, *shape = (gopindex.values(b.column(c)) for c in ("source_id", "gop_id", "width", "height", "fmt"))
        out += [(s, g, of, *p) for s, g, of, p in zip(source, gop, zip(*shape, strict=True), gopindex.packets_of(b.column("packets")), strict=True)]
    return out


def run_segments(spec: pa.Table, gops: pa.Table, config: EngineConfig) -> pa.Table:
    """``run_segment`` for whole segments, one after another: each by its own schedule and pool; what they render is evaluated together."""
    forest, by_gop, gop_of = kernels.Forest(spec.column("nodes")), {}, {}
    for source, gop, shape, idx, packets in _given(gops):
        by_gop[source, gop] = packets, shape, [(source, i) for i in idx]
        gop_of.update(dict.fromkeys(by_gop[source, gop][2], (source, gop)))
    needs, gens = forest.needs(), spec.column("gen").to_pylist()
    inputs: dict[int, dict] = {}
    done, out, waiting = [], [], 0

    def render():
        rows = list(inputs)
        out.extend(kernels.evaluate_many(forest, rows, lambda r, s, i: inputs[r][s, i]))
        done.extend(rows)
        inputs.clear()

    for _, rows in _by_segment(spec):
        run, frames, opened = plan([needs[r] for r in rows], gop_of.__getitem__, lambda g: by_gop[g][2], config)
        sources, held, deep = {}, {}, Counter([s[1] for s in run.steps if s[0] == "next"])
        for kind, k, *more in run.steps:
            if kind == "open":
                packets, shape, _ = by_gop[opened[more[0]]]
                sources[k] = codec.first_frames(packets, deep[k]), shape
            elif kind == "next":
                data = next(sources[k][0])
                if more[0] is not None:
                    held[more[0]] = (data, *sources[k][1])
            else:
                uses, given_up = more
                inputs[rows[k]] = {frames[f]: held[t] for f, t in uses}
                waiting += sum(len(held[t][0]) for _, t in uses)
                for t in given_up:
                    del held[t]
                if waiting >= WAITING:
                    render()
                    waiting = 0
    render()
    ids = spec.column("spec_id")[0].as_py() if len(gens) else ""
    return _rows([ids] * len(done), [gens[r] for r in done], out)


def _rows(ids: list, gens: list, rendered: list[tuple[int, int, str, bytes]]) -> pa.Table:
    cols = [ids, gens, *([x[k] for x in rendered] for k in range(4))]
    return pa.table([pa.array(c, t.type) for c, t in zip(cols, _OUT, strict=True)], schema=_OUT)


def segment_local(spec: DataFrame, gops: DataFrame, sources: DataFrame, gop_len: int | None, config: EngineConfig = EngineConfig(), together: int = TOGETHER) -> DataFrame:
    """Rendered frames (spec_id, gen, w, h, fmt, data). The catalogue is broadcast if it is small (counted), else joined.

    ``together`` segments are a task's group: their packets and expressions are in memory at once, so it is 1 for frames of real sizes."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        return run_segments(left, right, config)

    run_of = F.expr(f"seg div {together}")
    wanted = _touched(spec, gops, gop_len).select("spec_id", run_of.alias("run"), "source_id", "gop_id").distinct()
    given = wanted.join(_packed(gops, sources), ["source_id", "gop_id"]).select(F.col("spec_id").alias("for_spec"), F.col("run").alias("for_run"), "source_id", "gop_id", "packets", "width", "height", "fmt")
    return spec.select("spec_id", "seg", "gen", "nodes", run_of.alias("run")).groupBy("spec_id", "run").cogroup(given.groupBy("for_spec", "for_run")).applyInArrow(run, OUT)


def segment_stats(spec: DataFrame, gops: DataFrame, sources: DataFrame, gop_len: int | None, config: EngineConfig = EngineConfig()) -> DataFrame:
    """Counters per segment of the same run. They hang on the needs and the GOPs' packets only, so no pixel is read or decoded for them."""
    names = [c.split()[0] for c in STATS.split(", ")]
    run_of = F.expr(f"seg div {TOGETHER}")
    needs = schedule(spec).withColumn("run", run_of)
    wanted = _touched(spec, gops, gop_len).select("spec_id", run_of.alias("run"), "source_id", "gop_id").distinct()
    orders = gops.join(sized_broadcast(sources.select("source_id")), "source_id").select("source_id", "gop_id", F.col("packets.idx").alias("idx"))
    given = wanted.join(orders, ["source_id", "gop_id"]).select(F.col("spec_id").alias("for_spec"), F.col("run").alias("for_run"), "source_id", "gop_id", "idx")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        order = {(s, g): [(s, i) for i in idx] for s, g, idx in zip(*(right.column(c).to_pylist() for c in ("source_id", "gop_id", "idx")), strict=True)}
        gop_of = {f: g for g, frames in order.items() for f in frames}
        ids, segs, out = [], [], []
        for seg, gens in _by_segment(left):
            wants = [[(n["source"], n["idx"]) for n in needs] for needs in left.column("needs").take(gens).to_pylist()]
            ids.append(left.column("spec_id")[0].as_py())
            segs.append(seg)
            out.append(plan(wants, gop_of.__getitem__, order.__getitem__, config, False)[0].stats)
        return pa.table({"spec_id": pa.array(ids, pa.string()), "seg": pa.array(segs, pa.int64()), **{n: pa.array([s[n] for s in out], pa.int64()) for n in names}})

    return needs.groupBy("spec_id", "run").cogroup(given.groupBy("for_spec", "for_run")).applyInArrow(run, "spec_id string, seg bigint, " + STATS)


def _by_segment(rows: pa.Table) -> list[tuple[int, list[int]]]:
    """(segment, its rows in order of their generations), in order."""
    out: dict[int, list[int]] = {}
    segs, gens = rows.column("seg").to_pylist(), rows.column("gen").to_pylist()
    for k in sorted(range(len(gens)), key=gens.__getitem__):
        out.setdefault(segs[k], []).append(k)
    return sorted(out.items())


def _table(spec_id: str, rows: list[tuple]) -> pa.Table:
    cols = [[spec_id] * len(rows), [g for g, _ in rows], [kernels.size_of(f)[0] for _, f in rows], [kernels.size_of(f)[1] for _, f in rows], [f[0] for _, f in rows], [kernels.raw(f) for _, f in rows]]
    return pa.table([pa.array(c, t.type) for c, t in zip(cols, _OUT, strict=True)], schema=_OUT)


def decode_exchange(spec: DataFrame, gops: DataFrame, gop_len: int | None, block: int | None = None) -> DataFrame:
    """(spec_id, block, source_id, idx, raw): the needed frames, a copy for each block of generations that uses them; each GOP is opened once."""
    at = _touched(spec, gops, gop_len).select("source_id", "gop_id", "idx", "spec_id", F.expr(f"gen div {block or BLOCK}").alias("block")).distinct()
    wanted = at.groupBy("source_id", "gop_id").agg(F.collect_set("idx").alias("wanted"), F.collect_list(F.struct("idx", "spec_id", "block")).alias("uses"))
    deep = F.array_max(F.transform(F.filter("packets", lambda p: F.array_contains("wanted", p["idx"])), lambda p: p["dpos"]))
    frames = gopindex.decode_needed(gops.join(wanted, ["source_id", "gop_id"]).withColumn("upto", deep), "uses")
    return frames.withColumn("use", F.explode("uses")).select("use.spec_id", "use.block", "source_id", "idx", "raw")


def gop_exchange(spec: DataFrame, gops: DataFrame, sources: DataFrame, gop_len: int | None, block: int | None = None) -> DataFrame:
    """Rendered frames. A block's expressions meet the frames that they use, each there once, so no frame is copied to every generation.

    ``block`` generations are a task's group: their frames are in memory at once, so it is small for frames of real sizes."""
    block = block or BLOCK
    # pixels are never broadcast: what the optimiser takes for their size is that of the tables they are made from
    frames = decode_exchange(spec, gops, gop_len, block).join(sized_broadcast(sources.select("source_id", "width", "height", "fmt")), "source_id")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        source, idx, raw, w, h, fmt = (gopindex.values(right.column(c).combine_chunks()) for c in ("source_id", "idx", "raw", "width", "height", "fmt"))
        given = dict(zip(zip(source, idx), zip(raw, w, h, fmt), strict=True))
        forest, gens = kernels.Forest(left.column("nodes")), left.column("gen").to_pylist()
        rows, out = [r for r, needs in enumerate(forest.needs()) if any(n in given for n in needs)], []
        for at in range(0, len(rows), 1024):
            out += kernels.evaluate_many(forest, rows[at : at + 1024], lambda r, s, i: given[s, i])
        ids = left.column("spec_id")[0].as_py() if rows else ""
        return _rows([ids] * len(rows), [gens[r] for r in rows], out)

    blocks = spec.select("spec_id", "gen", "nodes", F.expr(f"gen div {block}").alias("block")).groupBy("spec_id", "block")
    dealt = frames.withColumnsRenamed({"spec_id": "for_spec", "block": "for_block"}).groupBy("for_spec", "for_block")
    return blocks.cogroup(dealt).applyInArrow(run, OUT)


def evaluate(joined: DataFrame) -> DataFrame:
    """(spec_id, gen, nodes, frames) -> rendered frames."""

    def run(it):
        for whole in it:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                forest, have = kernels.Forest(b.column(2)), b.column(3)
                ends = [0, *have.value_lengths().to_numpy().cumsum().tolist()]
                source, idx, raw, w, h, fmt = (f.to_pylist() for f in have.flatten().flatten())
                given = [{(source[k], idx[k]): (raw[k], w[k], h[k], fmt[k]) for k in range(*span)} for span in zip(ends, ends[1:])]
                out = kernels.evaluate_many(forest, list(range(b.num_rows)), lambda r, s, i, given=given: given[r][s, i])
                yield from _rows(b.column(0).to_pylist(), b.column(1).to_pylist(), out).to_batches()

    return joined.select("spec_id", "gen", F.col("nodes").cast(f"array<{NODE}>").alias("nodes"), "frames").mapInArrow(run, OUT)


def render(spec: DataFrame, gops: DataFrame, sources: DataFrame, gop_len: int | None, config: EngineConfig = EngineConfig(), plan: str = "auto", frame_bytes: int = 384) -> DataFrame:
    """The whole spec. 'auto' asks the cost rule (index statistics only, one small row to the driver)."""
    if plan == "auto":
        from reelspark.plans.cost import choose

        plan = choose(references(spec), gop_len, frame_bytes, gops=gops).first()["plan"]
    return segment_local(spec, gops, sources, gop_len, config) if plan == "segment_local" else gop_exchange(spec, gops, sources, gop_len)


def digests(rendered: DataFrame) -> DataFrame:
    """(spec_id, gen, w, h, fmt, md5): md5 of the comma-joined bytes, as SQL computes it."""
    def run(it):
        for b in it:
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(kernels.digests(b.column(5).to_pylist()), pa.string())], names=[*b.schema.names[:5], "md5"])

    return rendered.mapInArrow(run, "spec_id string, gen bigint, w int, h int, fmt string, md5 string")


def encoded(rendered: DataFrame, seg_frames: int) -> DataFrame:
    """Rendered frames as segments: one closed GOP each, in generation order."""
    frames = rendered.select("spec_id", F.expr(f"gen div {seg_frames}").alias("seg"), F.col("gen").alias("idx"), F.col("data").alias("raw"))

    def run(t: pa.Table) -> pa.Table:
        rows = sorted(zip(t.column("idx").to_pylist(), t.column("raw").to_pylist(), strict=True))
        return pa.table({"spec_id": [t.column("spec_id")[0].as_py()], "seg": [t.column("seg")[0].as_py()], "n": pa.array([len(rows)], pa.int32()), "packets": pa.array([codec.encode([r for _, r in rows], first=rows[0][0])], gopindex._packets())})

    return frames.groupBy("spec_id", "seg").applyInArrow(run, "spec_id string, seg bigint, n int, packets array<struct<dpos:int,idx:bigint,kind:string,bytes:binary>>")


__all__ = ["NODE", "decode_exchange", "digests", "encoded", "gop_exchange", "render", "run_segment", "segment_local", "segment_stats"]
