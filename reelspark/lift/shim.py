"""Replaying a draw script on symbols: no pixel is read, every written frame becomes an expression.

``Imaging`` has the calls a draw script uses (readers, writers, drawing functions) under plain names. Frames are
``SymFrame`` objects; drawing functions change their frame in place from the script's view, while below each call binds the
symbol to a new pure node. A frame shows three-byte pixels to the script and stays in its source's format until a filter needs them.
"""

from __future__ import annotations

import queue
import threading
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reelspark.engine.font import text_extent
from reelspark.model.expr import Tree
from reelspark.model.schemas import SPEC


@dataclass(frozen=True)
class ClipMeta:
    source_id: str
    width: int
    height: int
    fmt: str
    n_frames: int
    fps_num: int = 24
    fps_den: int = 1
    first: int = 0  # where a reader begins: a replay of a part of the clip


class ClipEnv:
    """The clips a script may open: name -> metadata (one bounded lookup, collected once)."""

    def __init__(self, clips: dict[str, ClipMeta], conversion: str = "lazy"):
        if conversion not in ("lazy", "eager"):
            raise ValueError(conversion)
        self.clips, self.conversion = clips, conversion

    @classmethod
    def of(cls, sources: DataFrame, names: list[str], conversion: str = "lazy") -> ClipEnv:
        rows = sources.where(sources["source_id"].isin(names)).select("source_id", "width", "height", "fmt", "n_frames", "fps_num", "fps_den").collect()
        return cls({r["source_id"]: ClipMeta(*r) for r in rows}, conversion)


class SymFrame:
    """A virtual pixel array: its construction, its size, and the format it has and shows."""

    def __init__(self, tree: Tree, width: int, height: int, true_fmt: str, present_fmt: str = "bgr24"):
        self.tree, self.width, self.height, self.true_fmt, self.present_fmt = tree, width, height, true_fmt, present_fmt

    dtype = "uint8"

    @property
    def shape(self) -> tuple[int, ...]:
        return (self.height, self.width) if self.present_fmt == "gray8" else (self.height, self.width, 3)

    def copy(self) -> SymFrame:
        return SymFrame(self.tree, self.width, self.height, self.true_fmt, self.present_fmt)

    def settle(self, fmt: str | None = None) -> Tree:
        """The tree in the wanted format (by default the one shown)."""
        fmt = fmt or self.present_fmt
        if self.true_fmt != fmt:
            self.tree, self.true_fmt = Tree("pixfmt", [self.tree], (), fmt), fmt
        return self.tree

    def _bind(self, op: str, *ints: int, text: str = "", others: tuple = ()) -> SymFrame:
        self.tree = Tree(op, [self.settle(), *others], ints, text)
        return self

    def _span(self, key) -> tuple[int, int, int, int]:
        ys, xs = key[:2] if isinstance(key, tuple) else (key, slice(None))
        y0, y1, _ = ys.indices(self.height)
        x0, x1, _ = xs.indices(self.width)
        return x0, y0, x1 - x0, y1 - y0

    def __getitem__(self, key) -> SymFrame:
        x, y, w, h = self._span(key)
        return SymFrame(Tree("crop", [self.settle()], (x, y, w, h)), w, h, self.present_fmt, self.present_fmt)

    def __setitem__(self, key, value: SymFrame) -> None:
        x, y, w, h = self._span(key)
        if (value.width, value.height) != (w, h):
            raise ValueError(f"can't put {value.width} x {value.height} pixels into {w} x {h}")
        self._bind("paste", x, y, others=(value.settle(self.present_fmt),))


class ClipReader:
    def __init__(self, env: ClipEnv, name: str):
        if name not in env.clips:
            raise FileNotFoundError(name)
        self.env, self.meta, self.at = env, env.clips[name], env.clips[name].first

    def read(self) -> tuple[bool, SymFrame | None]:
        if not self.meta.first <= self.at < self.meta.n_frames:
            return False, None
        m = self.meta
        frame = SymFrame(Tree("ref", (), (self.at,), m.source_id), m.width, m.height, m.fmt, "gray8" if m.fmt == "gray8" else "bgr24")
        if self.env.conversion == "eager":
            frame.settle()
        self.at += 1
        return True, frame

    def seek(self, i: int) -> None:
        self.at = i

    def position(self) -> int:
        return self.at

    def release(self) -> None:
        self.at = self.meta.n_frames


class ClipWriter:
    """Collects frames in order (unless it is not to ``keep`` them); ``push`` (if given) hears of each and of the end."""

    def __init__(self, fmt: str, push: Callable[[int | None, list[dict] | None], None] | None = None, keep: bool = True):
        self.fmt, self.push, self.keep, self.frames, self.written, self.closed = fmt, push, keep, [], 0, False

    def write(self, frame: SymFrame) -> None:
        if self.closed:
            raise ValueError("the writer is closed")
        nodes = frame.copy().settle(self.fmt).flatten()
        if self.keep:
            self.frames.append(nodes)
        self.written += 1
        if self.push:
            self.push(self.written - 1, nodes)

    def close(self) -> None:
        if not self.closed and self.push:
            self.push(None, None)
        self.closed = True

    release = close


def filter_op(f: Callable) -> Callable:
    """A drawing call: changes its first argument from the script's view and returns it."""

    def call(frame: SymFrame, *args, **kw) -> SymFrame:
        if not isinstance(frame, SymFrame):
            raise TypeError("a drawing call takes a frame")
        f(frame, *args, **kw)
        return frame

    call.__name__ = f.__name__
    return call


class Imaging:
    """What the imaging import gives a replayed script."""

    def __init__(self, env: ClipEnv, push: Callable | None = None, keep: bool = True):
        self.env, self.push, self.keep, self.writers = env, push, keep, []

    def open_clip(self, name: str) -> ClipReader:
        return ClipReader(self.env, name)

    def new_clip(self, fmt: str = "yuv420p") -> ClipWriter:
        self.writers.append(ClipWriter(fmt, self.push, self.keep))
        return self.writers[-1]

    text_extent = staticmethod(text_extent)  # outside the model: runs for real

    @staticmethod
    def grid(frames: list[SymFrame], cols: int) -> SymFrame:
        f = frames[0]
        rows = -(-len(frames) // cols)
        return SymFrame(Tree("grid", [x.settle(f.present_fmt) for x in frames], (cols,)), f.width * cols, f.height * rows, f.present_fmt, f.present_fmt)

    @staticmethod
    def resize(f: SymFrame, w: int, h: int, mode: int = 0) -> SymFrame:
        return SymFrame(Tree("resize", [f.settle()], (w, h, mode)), w, h, f.present_fmt, f.present_fmt)

    @staticmethod
    def flip(f: SymFrame, across: int = 1) -> SymFrame:
        return SymFrame(Tree("flip", [f.settle()], (across,)), f.width, f.height, f.present_fmt, f.present_fmt)

    @staticmethod
    def mix(a: SymFrame, b: SymFrame, alpha: int) -> SymFrame:
        return SymFrame(Tree("blend", [a.settle(), b.settle(a.present_fmt)], (alpha,)), a.width, a.height, a.present_fmt, a.present_fmt)

    @staticmethod
    def gray(f: SymFrame) -> SymFrame:
        return SymFrame(Tree("gray", [f.settle()]), f.width, f.height, f.present_fmt, f.present_fmt)

    @staticmethod
    @filter_op
    def text(f: SymFrame, s: str, at: tuple[int, int], color=(255, 255, 255), scale: int = 1) -> None:
        f._bind("text", *at, *color, scale, text=str(s))

    @staticmethod
    @filter_op
    def box(f: SymFrame, a: tuple[int, int], b: tuple[int, int], color=(255, 255, 255), thick: int = 1) -> None:
        f._bind("box", *a, *b, *color, thick)

    @staticmethod
    @filter_op
    def corners(f: SymFrame, a: tuple[int, int], b: tuple[int, int], color=(255, 255, 255), reach: int = 3) -> None:
        f._bind("corners", *a, *b, *color, reach)

    @staticmethod
    @filter_op
    def tint(f: SymFrame, a: tuple[int, int], b: tuple[int, int], color, alpha: int) -> None:
        f._bind("tint", *a, *b, *color, alpha)

    @staticmethod
    @filter_op
    def line(f: SymFrame, a: tuple[int, int], b: tuple[int, int], color=(255, 255, 255)) -> None:
        f._bind("line", *a, *b, *color)

    @staticmethod
    @filter_op
    def circle(f: SymFrame, at: tuple[int, int], radius: int, color=(255, 255, 255)) -> None:
        f._bind("circle", *at, radius, *color)

    @staticmethod
    @filter_op
    def mask(f: SymFrame, m: SymFrame, color, alpha: int = 96) -> None:
        f._bind("mask", *color, alpha, others=(m.settle("gray8"),))

    @staticmethod
    @filter_op
    def heat(f: SymFrame, m: SymFrame, alpha: int = 96) -> None:
        f._bind("heat", alpha, others=(m.settle("gray8"),))


def run(script: Callable[[Imaging], None], env: ClipEnv, push: Callable | None = None) -> list[list[dict]]:
    """The frames that a script writes (of all its writers, in order of opening), as node lists."""
    imaging = Imaging(env, push)
    script(imaging)
    Tree.forget()
    return [nodes for w in imaging.writers for nodes in w.frames]


def as_spec(spark: SparkSession, frames: list[list[dict]], spec_id: str = "script", seg_frames: int = 48) -> DataFrame:
    rows = [(spec_id, g, g // seg_frames, [(n["op"], n["kids"], n["ints"], n["text"]) for n in nodes]) for g, nodes in enumerate(frames)]
    return spark.createDataFrame(rows, SPEC)


_INTS = pa.list_(pa.int64())
_NODE = pa.struct([("op", pa.string()), ("kids", pa.list_(pa.int32())), ("ints", _INTS), ("text", pa.string())])
_SPEC = pa.schema([("spec_id", pa.string()), ("gen", pa.int64()), ("seg", pa.int64()), ("nodes", pa.list_(_NODE))])
FLUSH = 2048  # frames a batch: what a streamed replay holds


def spec_batch(frames: list[tuple[int, list[dict]]], spec_id: str, seg_frames: int) -> pa.RecordBatch:
    """(gen, nodes) as rows of a spec, column by column."""
    nodes = [n for _, of in frames for n in of]

    def lists(rows: list[list[int]], kind: pa.DataType) -> pa.Array:
        ends = [0]
        for r in rows:
            ends.append(ends[-1] + len(r))
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array([x for r in rows for x in r], kind))

    at = [0]
    for _, of in frames:
        at.append(at[-1] + len(of))
    fields = [pa.array([n["op"] for n in nodes], pa.string()), lists([n["kids"] for n in nodes], pa.int32()), lists([n["ints"] for n in nodes], pa.int64()), pa.array([n["text"] for n in nodes], pa.string())]
    values = pa.StructArray.from_arrays(fields, fields=list(_NODE))
    gens = [g for g, _ in frames]
    columns = [pa.array([spec_id] * len(gens), pa.string()), pa.array(gens, pa.int64()), pa.array([g // seg_frames for g in gens], pa.int64()), pa.ListArray.from_arrays(pa.array(at, pa.int32()), values)]
    return pa.RecordBatch.from_arrays(columns, schema=_SPEC)


class _Ended(BaseException):
    """Nobody takes the frames any more."""


def stream(script: Callable[[Imaging], None], env: ClipEnv, spec_id: str = "script", seg_frames: int = 48) -> Iterator[pa.RecordBatch]:
    """What ``run`` gives, in batches while the script runs in a thread: two batches and the script's own frames are held.

    Writers are numbered through in order of opening, so each has to be done when the next one's first frame is written."""
    ready: queue.Queue = queue.Queue(1)
    over = threading.Event()
    held: list[tuple[int, list[dict]]] = []

    def put(item) -> None:
        while not over.is_set():
            try:
                return ready.put(item, timeout=0.1)
            except queue.Full:
                continue
        raise _Ended

    current, total = 0, 0

    def take(writer: int, nodes: list[dict] | None) -> None:
        nonlocal current, total
        if nodes is None:
            return
        if writer < current:
            raise ValueError("a writer goes on after a later one has begun")
        current = writer
        held.append((total, nodes))
        total += 1
        if len(held) >= FLUSH:
            put(spec_batch(held, spec_id, seg_frames))
            held.clear()

    class Streamed(Imaging):
        def new_clip(self, fmt: str = "yuv420p") -> ClipWriter:
            k = len(self.writers)
            self.writers.append(ClipWriter(fmt, lambda _, nodes: take(k, nodes), keep=False))
            return self.writers[-1]

    def replay() -> None:
        try:
            script(Streamed(env))
            if held:
                put(spec_batch(held, spec_id, seg_frames))
            put(None)
        except _Ended:
            pass
        except BaseException as e:  # noqa: BLE001  what the script raises is raised where its frames are taken
            try:
                put(e)
            except _Ended:
                pass

    worker = threading.Thread(target=replay, daemon=True)
    worker.start()
    try:
        while (item := ready.get()) is not None:
            if isinstance(item, BaseException):
                raise item
            yield item
    finally:
        over.set()
        worker.join()


def replayed(script: Callable[[Imaging], None], env: ClipEnv, index: DataFrame, spec_id: str = "script", seg_frames: int = 48) -> DataFrame:
    """The spec of a script, replayed from its first frame to its last in one task, as it would run; frames leave it in batches.

    ``index``: a row (source_id, idx) for every frame of the clips; the task counts them, and that is how long the clips are."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lengths: Counter[str] = Counter()
        for b in it:
            for v in b.column(0).value_counts().to_pylist():
                lengths[v["values"]] += v["counts"]
        clips = {name: replace(m, n_frames=lengths[name]) for name, m in env.clips.items()}
        yield from stream(script, ClipEnv(clips, env.conversion), spec_id, seg_frames)

    return index.select("source_id", "idx").coalesce(1).mapInArrow(run, SPEC)


def replayed_in_parts(script: Callable[[Imaging, Callable], None], env: ClipEnv, name: str, index: DataFrame, given: DataFrame, spec_id: str = "script", seg_frames: int = 48, block: int = 4096) -> DataFrame:
    """The spec of a script that keeps nothing from one frame to the next: replayed for every block of a clip's frames in a task of its own.

    ``index``: idx of the clip's frames; ``given``: rows with ``frame`` that the script asks for by ``rows(frame)``, in order of ``ord``. A reader
    begins at the block's first frame and ends behind its last; a gap in the clip ends one replay and begins another."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        at = sorted(left.column("idx").to_pylist())
        rows: dict[int, list[dict]] = {}
        for r in right.sort_by([("frame", "ascending"), ("ord", "ascending")]).to_pylist():
            rows.setdefault(r["frame"], []).append(r)
        out: list[tuple[int, list[dict]]] = []
        begin = 0
        for k in range(1, len(at) + 1):
            if k == len(at) or at[k] != at[k - 1] + 1:
                part = ClipEnv({**env.clips, name: replace(env.clips[name], first=at[begin], n_frames=at[k - 1] + 1)}, env.conversion)
                imaging = Imaging(part, lambda gen, nodes, lo=at[begin]: nodes is not None and out.append((lo + gen, nodes)), keep=False)
                script(imaging, lambda frame: rows.get(frame, ()))
                begin = k
        return pa.Table.from_batches([spec_batch(out, spec_id, seg_frames)])

    frames = index.select("idx", (F.col("idx") - F.pmod("idx", F.lit(block))).alias("block"))
    dets = given.withColumn("for_block", F.col("frame") - F.pmod("frame", F.lit(block)))
    return frames.groupBy("block").cogroup(dets.groupBy("for_block")).applyInArrow(run, SPEC)
