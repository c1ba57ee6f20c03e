"""Frame types bottom-up, and static policy, as one fold per expression.

A type is (w, h, fmt). The first error of an expression is reported; an expression is fine if its root has
the type that its spec promises. Sources are looked up by a join, so a large catalogue is no driver object.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_TYPE = "struct<w:bigint,h:bigint,fmt:string,err:string>"
#: Kids and integer constants each operation takes; -1: any number.
ARITY = {
    "ref": (0, 1), "pixfmt": (1, 0), "identity": (1, 0), "copy": (1, 0), "box": (1, 8), "corners": (1, 8), "tint": (1, 8), "text": (1, 6), "line": (1, 7), "circle": (1, 6),
    "mask": (2, 4), "heat": (2, 1), "grid": (-1, 1), "resize": (1, 3), "crop": (1, 4), "paste": (2, 2), "flip": (1, 1), "blend": (2, 1), "gray": (1, 0),
}
DRAWS = ["box", "corners", "tint", "text", "line", "circle", "mask", "heat"]
FORMATS = ["yuv420p", "bgr24", "rgb24", "gray8"]


def _type(w, h, fmt, err) -> Column:
    lit = lambda v: v if isinstance(v, Column) else F.lit(v)
    return F.struct(lit(w).cast("bigint").alias("w"), lit(h).cast("bigint").alias("h"), lit(fmt).cast("string").alias("fmt"), lit(err).cast("string").alias("err"))


def _fold(nodes: Column, sources: Column) -> Column:
    arity_kids = F.create_map(*[F.lit(x) for k, (a, _) in ARITY.items() for x in (k, a)])
    arity_ints = F.create_map(*[F.lit(x) for k, (_, b) in ARITY.items() for x in (k, b)])

    def step(acc: Column, n: Column) -> Column:
        kid = lambda k: F.get(acc, F.get(n["kids"], F.lit(k)))
        a, b = kid(0), kid(1)
        num = lambda k: F.get(n["ints"], F.lit(k))
        op = n["op"]
        src = F.try_element_at(sources, n["text"])
        below = F.array_compact(F.transform(n["kids"], lambda k: F.get(acc, k)["err"]))
        known = F.try_element_at(arity_kids, op)
        kids_ok = (known == F.size(n["kids"])) | ((known == -1) & (F.size(n["kids"]) > 0))
        err = (
            F.when(known.isNull(), F.lit("unknown filter"))
            .when(~kids_ok | (F.try_element_at(arity_ints, op) != F.size(n["ints"])), F.lit("wrong arguments"))
            .when((op == "ref") & src.isNull(), F.lit("unknown source"))
            .when((op == "ref") & ((num(0) < 0) | (num(0) >= src["n_frames"])), F.lit("frame out of range"))
            .when(F.size(below) > 0, F.get(below, F.lit(0)))
            .when((op == "pixfmt") & ~n["text"].isin(FORMATS), F.lit("unknown format"))
            .when(op.isin(DRAWS) & (a["fmt"] == "yuv420p"), F.lit("wrong format"))
            .when(op.isin("mask", "heat") & (b["fmt"] != "gray8"), F.lit("wrong format"))
            .when(op.isin("heat") & (a["fmt"] == "gray8"), F.lit("wrong format"))
            .when(op.isin("blend") & ((a["fmt"] != b["fmt"]) | (a["w"] != b["w"]) | (a["h"] != b["h"])), F.lit("sizes differ"))
            .when((op == "grid") & F.exists(n["kids"], lambda k: (F.get(acc, k)["fmt"] != a["fmt"]) | (F.get(acc, k)["w"] != a["w"]) | (F.get(acc, k)["h"] != a["h"])), F.lit("sizes differ"))
            .when(op.isin("resize", "crop") & (F.least(F.when(op == "resize", num(0)).otherwise(num(2)), F.when(op == "resize", num(1)).otherwise(num(3))) < 1), F.lit("empty frame"))
        )
        rows = F.ceil(F.size(n["kids"]) / num(0))
        w = F.when(op == "ref", src["width"]).when(op == "grid", a["w"] * num(0)).when(op == "resize", num(0)).when(op == "crop", num(2)).otherwise(a["w"])
        h = F.when(op == "ref", src["height"]).when(op == "grid", a["h"] * rows).when(op == "resize", num(1)).when(op == "crop", num(3)).otherwise(a["h"])
        fmt = F.when(op == "ref", src["fmt"]).when(op == "pixfmt", n["text"]).otherwise(a["fmt"])
        err = F.coalesce(err, F.when((fmt == "yuv420p") & ((w % 2 == 1) | (h % 2 == 1)), F.lit("odd size")))  # chroma samples stand for 2 x 2 pixels
        return F.concat(acc, F.array(_type(w, h, fmt, err)))

    return F.aggregate(nodes, F.array().cast(f"array<{_TYPE}>"), step)


def typed(spec: DataFrame, sources: DataFrame) -> DataFrame:
    """The spec with ``types``, one per node. Catalogue rows are joined by source name and gathered per generation."""
    names = spec.select("spec_id", "gen", F.explode(F.array_distinct(F.transform(F.filter("nodes", lambda n: n["op"] == "ref"), lambda n: n["text"]))).alias("source_id"))
    facts = names.join(sources.select("source_id", "width", "height", "fmt", "n_frames"), "source_id").groupBy("spec_id", "gen").agg(F.map_from_entries(F.collect_list(F.struct("source_id", F.struct("width", "height", "fmt", "n_frames")))).alias("sources"))
    joined = spec.join(facts, ["spec_id", "gen"], "left")
    empty = F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<struct<width:int,height:int,fmt:string,n_frames:bigint>>"))
    return joined.withColumn("types", _fold(F.col("nodes"), F.coalesce("sources", empty))).drop("sources")


def infer(spec: DataFrame, sources: DataFrame, want: tuple[int, int, str] | None = None) -> DataFrame:
    """spec_id, gen, ok, err, w, h, fmt of every generation."""
    root = F.element_at("types", -1)
    out = typed(spec, sources).select("spec_id", "gen", root.alias("t"))
    err = F.col("t.err")
    if want:
        err = F.coalesce(err, F.when((F.col("t.w") != want[0]) | (F.col("t.h") != want[1]) | (F.col("t.fmt") != want[2]), F.lit("wrong output type")))
    return out.select("spec_id", "gen", err.isNull().alias("ok"), F.coalesce(err, F.lit("")).alias("err"), "t.w", "t.h", "t.fmt")


@dataclass(frozen=True)
class Policy:
    max_pixels: int = 4096 * 2160
    max_const_bytes: int = 4096
    max_depth: int = 64
    max_nodes: int = 512
    max_refs: int = 96


def depths(nodes: Column) -> Column:
    return F.array_max(F.aggregate(nodes, F.array().cast("array<int>"), lambda acc, n: F.concat(acc, F.array(F.lit(1) + F.coalesce(F.array_max(F.transform(n["kids"], lambda k: F.get(acc, k))), F.lit(0))))))


def const_bytes(nodes: Column) -> Column:
    return F.aggregate(F.filter(nodes, lambda n: n["op"] != "ref"), F.lit(0).cast("bigint"), lambda a, n: a + 8 * F.size(n["ints"]) + F.length(n["text"]))


def facts(spec: DataFrame) -> DataFrame:
    refs = F.size(F.array_distinct(F.transform(F.filter("nodes", lambda n: n["op"] == "ref"), lambda n: F.struct(n["text"], n["ints"]))))
    return spec.select("spec_id", "gen", F.size("nodes").cast("bigint").alias("n_nodes"), refs.cast("bigint").alias("n_refs"), depths(F.col("nodes")).cast("bigint").alias("depth"), const_bytes(F.col("nodes")).alias("const_bytes"))


def enforce(spec: DataFrame, policy: Policy = Policy(), sources: DataFrame | None = None) -> DataFrame:
    """spec_id, gen, ok, err: static limits only, nothing is rendered."""
    out = facts(spec)
    err = F.when(F.col("n_nodes") > policy.max_nodes, "too many nodes").when(F.col("depth") > policy.max_depth, "too deep").when(F.col("const_bytes") > policy.max_const_bytes, "constants too large").when(F.col("n_refs") > policy.max_refs, "too many inputs")
    if sources is not None:
        sizes = typed(spec, sources).select("spec_id", "gen", F.array_max(F.transform("types", lambda t: t["w"] * t["h"])).alias("pixels"))
        out = out.join(sizes, ["spec_id", "gen"])
        err = err.when(F.col("pixels") > policy.max_pixels, "frame too large")
    return out.select("spec_id", "gen", err.isNull().alias("ok"), F.coalesce(err, F.lit("")).alias("err"))
