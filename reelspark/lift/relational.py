"""Set-oriented lifting: frames left-joined with detections give one expression per generation.

One shuffle (on the frame key) replaces a script's filter of the whole detections table per frame; frames
without a detection stay. The expression is built by column functions alone.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reelspark.model.expr import node, ref
from reelspark.model.schemas import NODE
from reelspark.sources.derive import COLORS

WHITE, ALPHA, REACH = (255, 255, 255), 96, 3


def color(cls: Column) -> list[Column]:
    def channel(k: int) -> Column:
        out = F.lit(255)
        for name, bgr in COLORS.items():
            out = F.when(cls == name, bgr[k]).otherwise(out)
        return out

    return [channel(k) for k in range(3)]


def _tag(d: Column, prev: Column) -> list[Column]:
    """A filled tag at the box, then the text on it."""
    return [
        node("box", [prev], [d["x1"], d["y1"], d["x1"] + 4 * F.length(d["text"]), d["y1"] + 6, *color(d["cls"]), -1]),
        node("text", [prev + 1], [d["x1"] + 1, d["y1"] + 1, *WHITE, 1], d["text"]),
    ]


def _box(d: Column, prev: Column) -> list[Column]:
    return [node("box", [prev], [d["x1"], d["y1"], d["x2"], d["y2"], *color(d["cls"]), 1])]


def _corners(d: Column, prev: Column) -> list[Column]:
    return [node("corners", [prev], [d["x1"], d["y1"], d["x2"], d["y2"], *color(d["cls"]), REACH])]


def _tint(d: Column, prev: Column) -> list[Column]:
    return [node("tint", [prev], [d["x1"], d["y1"], d["x2"], d["y2"], *color(d["cls"]), ALPHA])]


def _mask(d: Column, prev: Column) -> list[Column]:
    return [ref("masks", d["mask_id"]), node("mask", [prev, prev + 1], [*color(d["cls"]), ALPHA])]


#: What each recipe draws for a detection, given the position of the node it draws on.
RECIPES: dict[str, list[Callable[[Column, Column], list[Column]]]] = {
    "label": [_tag], "box": [_box], "box_label": [_box, _tag], "corner": [_corners], "corner_label": [_corners, _tag], "color": [_tint], "color_label": [_tint, _tag], "mask": [_mask], "mask_label": [_mask, _tag],
}


def drawn(d: Column, recipe: str, prev: Column) -> Column:
    out: list[Column] = []
    for part in RECIPES[recipe]:
        out += part(d, prev + len(out))
    return F.array(*out)


def nodes_of(recipe: str, size: int) -> Callable[[Column], Column]:
    return lambda d: drawn(d, recipe, F.lit(1) + (d["ord"] - 1) * size)


def size_of(recipe: str) -> int:
    return sum({_tag: 2, _box: 1, _corners: 1, _tint: 1, _mask: 2}[p] for p in RECIPES[recipe])


def annotate(frames: DataFrame, dets: DataFrame, recipe: str, spec_id: str = "spec", seg_frames: int = 48, fmt: str = "yuv420p", conversion: str = "lazy", needed: bool = False) -> DataFrame:
    """``frames``: gen, source_id, idx; ``dets``: frame, ord (1..n), geometry, cls, text, mask_id. Returns spec rows.

    ``lazy``: the native format stays until a filter asks for another; ``eager``: converted at read and at write.
    ``needed`` adds the needs, told from what is drawn, so that plans over references build no expression for them.
    """
    return expressed(listed(frames, dets), recipe, spec_id, seg_frames, fmt, conversion, needed)


def listed(frames: DataFrame, dets: DataFrame) -> DataFrame:
    """``frames`` with the list of their detections in order (null: none)."""
    cols = [c for c in dets.columns if c != "frame"]
    per_frame = dets.groupBy("frame").agg(F.array_sort(F.collect_list(F.struct("ord", *[c for c in cols if c != "ord"]))).alias("dets"))
    return frames.join(per_frame, frames["gen"] == per_frame["frame"], "left").select(*[frames[c] for c in frames.columns], "dets")


def expressed(joined: DataFrame, recipe: str, spec_id: str = "spec", seg_frames: int = 48, fmt: str = "yuv420p", conversion: str = "lazy", needed: bool = False) -> DataFrame:
    """The expressions of ``listed`` frames, row by row."""
    none = F.array().cast(joined.schema["dets"].dataType)
    size = size_of(recipe)
    body = F.flatten(F.transform(F.coalesce("dets", none), nodes_of(recipe, size)))
    n = F.coalesce(F.size("dets"), F.lit(0)) * size
    source = F.array(ref(F.col("source_id"), F.col("idx")))
    full = F.concat(source, F.array(node("pixfmt", [0], (), "bgr24")), body, F.array(node("pixfmt", [F.greatest(n, F.lit(0)) + 1], (), fmt)))
    nodes = full if conversion == "eager" else F.when(F.coalesce(F.size("dets"), F.lit(0)) > 0, full).otherwise(source)
    out = [F.lit(spec_id).alias("spec_id"), "gen", F.expr(f"gen div {seg_frames}").alias("seg"), nodes.alias("nodes")]
    if needed:
        needs = F.array(F.struct(F.col("source_id").alias("source"), F.col("idx").cast("bigint").alias("idx")))
        if _mask in RECIPES[recipe]:
            masks = F.transform(F.coalesce("dets", none), lambda d: F.struct(F.lit("masks").alias("source"), d["mask_id"].cast("bigint").alias("idx")))
            needs = F.array_sort(F.array_distinct(F.concat(needs, masks)))
        out.append(needs.alias("needs"))
    return joined.select(*out)


def sequence_spec(frames: DataFrame, spec_id: str, seg_frames: int) -> DataFrame:
    """A spec of bare references: clips, reversals, samples and compilations."""
    return frames.select(F.lit(spec_id).alias("spec_id"), "gen", F.expr(f"gen div {seg_frames}").alias("seg"), F.array(ref(F.col("source_id"), F.col("idx"))).alias("nodes"))


def grid_spec(cells: DataFrame, spec_id: str, seg_frames: int, cols: int = 2) -> DataFrame:
    """Several inputs side by side: ``cells``: gen, cell, source_id, idx."""
    refs = F.transform(F.array_sort(F.collect_list(F.struct("cell", "source_id", "idx"))), lambda c: ref(c["source_id"], c["idx"]))
    g = cells.groupBy("gen").agg(refs.alias("refs"))
    kids = F.sequence(F.lit(0), F.size("refs") - 1)
    top = F.struct(F.lit("grid").alias("op"), kids.alias("kids"), F.array(F.lit(cols).cast("bigint")).alias("ints"), F.lit("").alias("text")).cast(NODE)
    return g.select(F.lit(spec_id).alias("spec_id"), "gen", F.expr(f"gen div {seg_frames}").alias("seg"), F.concat("refs", F.array(top)).alias("nodes"))
