"""GOPs as rows: encoding by group, decoding, and the index that plans need (no pixels in it)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reelspark.model.schemas import GOPS, PACKET
from reelspark.sources import codec
from reelspark.sources.derive import GOP_LEN


#: GOPs of small frames that travel together (a task holds them at once); 1 for frames of real sizes.
TOGETHER = 16


def encode(frames: DataFrame, gop_len: int = GOP_LEN, b_run: int = 0, all_intra: bool = False, together: int = TOGETHER) -> DataFrame:
    """(source_id, idx, raw) -> one row per GOP. One shuffle on (source, run of GOPs), so long sources are many groups."""

    def run(t: pa.Table) -> pa.Table:
        dealt: dict[int, list[tuple[int, bytes]]] = {}
        for row in sorted(zip(t.column("idx").to_pylist(), t.column("raw").to_pylist(), strict=True)):
            dealt.setdefault(-(-row[0] // gop_len) if row[0] < 0 else row[0] // gop_len, []).append(row)  # as SQL divides: towards zero
        gops = []
        for rows in dealt.values():
            packets = codec.encode([r for _, r in rows], b_run, all_intra)
            for p in packets:  # a clip may have gaps (an hour without an event has no raster)
                p["idx"] = rows[p["idx"]][0]
            gops.append(packets)
        firsts, n = [rows[0][0] for rows in dealt.values()], [len(rows) for rows in dealt.values()]
        return pa.table({"source_id": [t.column("source_id")[0].as_py()] * len(gops), "gop_id": pa.array(list(dealt), pa.int64()), "first_idx": pa.array(firsts, pa.int64()), "n": pa.array(n, pa.int32()), "packets": pa.array(gops, _packets())})

    return frames.groupBy("source_id", F.expr(f"idx div {gop_len} div {together}").alias("run")).applyInArrow(run, GOPS)


def _packets() -> pa.DataType:
    return pa.list_(pa.struct([("dpos", pa.int32()), ("idx", pa.int64()), ("kind", pa.string()), ("bytes", pa.binary())]))


def values(column: pa.Array) -> list:
    """An Arrow column as a list; numbers and repeated texts without a scalar each."""
    if pa.types.is_integer(column.type) and not column.null_count:
        return column.to_numpy(zero_copy_only=False).tolist()
    if pa.types.is_string(column.type) and not column.null_count:
        coded = column.dictionary_encode()
        return list(map(coded.dictionary.to_pylist().__getitem__, coded.indices.to_numpy(zero_copy_only=False).tolist()))
    return column.to_pylist()


def packets_of(column: pa.Array) -> list[tuple[list[int], list[tuple[str, bytes]]]]:
    """(indices, (kind, bytes) of packets) of each row of a column of packets."""
    flat, ends = column.flatten(), [0, *column.value_lengths().to_numpy(zero_copy_only=False).cumsum().tolist()]
    idx, kinds, data = (values(flat.field(c)) for c in ("idx", "kind", "bytes"))
    packets = list(zip(kinds, data, strict=True))
    return [(idx[a:b], packets[a:b]) for a, b in zip(ends, ends[1:], strict=False)]


def _by_frame(uses: pa.Array, frames: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Which of a GOP's uses are each frame's: places one frame after another, and how many each has."""
    idx = uses.field("idx").to_numpy(zero_copy_only=False)
    order, at = np.argsort(idx, kind="stable"), np.array(frames, np.int64)
    lo, hi = (np.searchsorted(idx, at, side, sorter=order) for side in ("left", "right"))
    return np.concatenate([order[a:b] for a, b in zip(lo.tolist(), hi.tolist(), strict=True)] or [order[:0]]), hi - lo


def decode(gops: DataFrame) -> DataFrame:
    """All frames of all GOPs, each GOP decoded once."""
    return decode_needed(gops.withColumn("upto", F.col("n") - 1).withColumn("wanted", F.lit(None).cast("array<bigint>")))


def decode_needed(gops: DataFrame, carry: str | None = None) -> DataFrame:
    """GOPs with ``upto`` (deepest packet) and ``wanted`` (indices; null: all) -> (source_id, idx, raw), decoding no packet beyond.

    ``carry``: an array of structs with ``idx``; each frame gets the elements of its own index."""
    from pyspark.sql.pandas.types import to_arrow_type

    fields = ["source_id", "packets", "upto", "wanted", *([carry] if carry else [])]
    kind = gops.schema[carry].dataType if carry else None
    arrow = to_arrow_type(kind) if carry else None

    def run(it):
        for b in it:
            for k, (s, (idx, packets), upto, wanted) in enumerate(zip(values(b.column(0)), packets_of(b.column(1)), values(b.column(2)), b.column(3), strict=True)):
                keep = set(wanted.values.to_numpy(zero_copy_only=False).tolist()) if wanted.is_valid else None
                out = [(i, r) for i, r in zip(idx, codec.first_frames(packets, len(packets) if upto is None else upto + 1), strict=False) if keep is None or i in keep]
                columns = [pa.array([s] * len(out), pa.string()), pa.array([i for i, _ in out], pa.int64()), pa.array([r for _, r in out], pa.binary())]
                if carry:
                    uses = b.column(4)[k].values
                    places, many = _by_frame(uses, [i for i, _ in out])
                    columns.append(pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]), pa.int32()), uses.take(pa.array(places))).cast(arrow))
                yield pa.RecordBatch.from_arrays(columns, names=["source_id", "idx", "raw", *fields[4:]])

    return gops.select(*fields).mapInArrow(run, "source_id string, idx bigint, raw binary" + (f", {carry} {kind.simpleString()}" if carry else ""))


def index(gops: DataFrame) -> DataFrame:
    """(source_id, gop_id, first_idx, n, bytes, idx -> dpos)."""
    return gops.select("source_id", "gop_id", "first_idx", "n", F.aggregate("packets", F.lit(0).cast("bigint"), lambda a, p: a + F.length(p["bytes"])).alias("bytes"), F.map_from_entries(F.transform("packets", lambda p: F.struct(p["idx"], p["dpos"]))).alias("depth"))


def frame_index(gops: DataFrame) -> DataFrame:
    """(source_id, idx, gop_id, dpos): where each frame stands, whatever the GOPs' lengths, gaps and packet kinds; no pixels."""
    return gops.select("source_id", "gop_id", F.explode(F.transform("packets", lambda p: F.struct(p["idx"].alias("idx"), p["dpos"].alias("dpos")))).alias("p")).select("source_id", "p.idx", "gop_id", "p.dpos")


def depth(idx: Column, gop_len: int) -> Column:
    """Decode position of a frame where GOPs hold I and P frames only."""
    return F.pmod(idx, F.lit(gop_len))


__all__ = ["PACKET", "decode", "decode_needed", "depth", "encode", "index"]
