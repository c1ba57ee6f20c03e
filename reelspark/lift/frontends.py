"""Other ways to write a spec: filter-graph strings and edit lists."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.model.expr import Tree, ref

#: Filters of a graph string: operation and how its numbers are ordered.
_GRAPH = {"box": ("box", 8), "tint": ("tint", 8), "corners": ("corners", 8), "scale": ("resize", 3), "crop": ("crop", 4), "flip": ("flip", 1), "format": ("pixfmt", 0), "gray": ("gray", 0), "null": ("identity", 0), "text": ("text", 6)}


def parse_graph(text: str, source: str, idx: int) -> Tree:
    """A chain like ``format=bgr24,box=1:1:5:5:0:0:255:1,text='hi':2:2:255:255:255:1`` over one frame."""
    t = Tree("ref", (), (idx,), source)
    for step in _split(text, ","):
        name, _, args = step.strip().partition("=")
        if name not in _GRAPH:
            raise ValueError(f"unknown filter {name!r}")
        op, count = _GRAPH[name]
        parts = _split(args, ":") if args else []
        label = ""
        if op in ("pixfmt", "text"):
            label, parts = parts[0].strip("'"), parts[1:]
        if len(parts) != count:
            raise ValueError(f"{name} takes {count} numbers, not {len(parts)}")
        t = Tree(op, [t], [int(p) for p in parts], label)
    return t


def _split(text: str, by: str) -> list[str]:
    out, quoted = [""], False
    for ch in text:
        quoted ^= ch == "'"
        if ch == by and not quoted:
            out.append("")
        else:
            out[-1] += ch
    return [x for x in out if x]


def compile_edits(edits: DataFrame, spec_id: str, seg_frames: int = 48) -> DataFrame:
    """An edit list (pos, source_id, cut_in, cut_out) -> spec: the clips one after another, cut_out excluded.

    Offsets come from a window over the edits (a list made by hand is small); frames come from an explode.
    """
    from pyspark.sql import Window

    n = F.col("cut_out") - F.col("cut_in")
    placed = edits.where(n > 0).withColumn("first", F.sum(n).over(Window.orderBy("pos")) - n)
    rows = placed.select("source_id", "first", "cut_in", F.posexplode(F.sequence(F.col("cut_in"), F.col("cut_out") - 1)).alias("k", "idx"))
    gen = (F.col("first") + F.col("k")).cast("bigint")
    return rows.select(F.lit(spec_id).alias("spec_id"), gen.alias("gen"), F.floor(gen / seg_frames).cast("bigint").alias("seg"), F.array(ref(F.col("source_id"), F.col("idx"))).alias("nodes"))
