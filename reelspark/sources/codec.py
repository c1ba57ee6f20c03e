"""A small lossless inter-frame codec: it keeps the property that matters, GOP-dependent decode cost.

I packets hold a compressed raw frame; P packets the difference from the anchor before (mod 256); B
packets the difference from the mean of the anchors on both sides. Packets stand in decode order:
an anchor before the B frames that need it.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np

LEVEL = 1


def decode_order(n: int, b_run: int = 0) -> list[tuple[int, str, int, int]]:
    """(display position, kind, anchor before, anchor after) of a GOP of n frames, in decode order."""
    out, anchor, at = [(0, "I", -1, -1)], 0, 1
    while at < n:
        close = min(at + b_run, n - 1)
        out.append((close, "P", anchor, -1))
        out += [(k, "B", anchor, close) for k in range(at, close)]
        anchor, at = close, close + 1
    return out[: max(n, 0)]


def encode(frames: list[bytes], b_run: int = 0, all_intra: bool = False, first: int = 0) -> list[dict]:
    data = [np.frombuffer(f, np.uint8) for f in frames]
    order = [(k, "I", -1, -1) for k in range(len(frames))] if all_intra else decode_order(len(frames), b_run)
    out = []
    for dpos, (k, kind, a, b) in enumerate(order):
        base = 0 if kind == "I" else data[a] if kind == "P" else ((data[a].astype(np.int16) + data[b]) >> 1).astype(np.uint8)
        out.append({"dpos": dpos, "idx": first + k, "kind": kind, "bytes": zlib.compress((data[k] - base).tobytes(), LEVEL)})
    return out


def decode(packets: list[dict], upto: int | None = None) -> Iterator[tuple[int, bytes]]:
    """(index, raw frame) in decode order, up to and with the packet at position ``upto``."""
    before = last = None  # the anchors on both sides of a B packet
    for p in packets[: None if upto is None else upto + 1]:
        kind, value = p["kind"], np.frombuffer(zlib.decompress(p["bytes"]), np.uint8)
        if kind == "P":
            value = value + last
        elif kind == "B":
            value = value + ((before.astype(np.int16) + last) >> 1).astype(np.uint8)
        if kind != "B":
            before, last = last, value
        yield p["idx"], value.tobytes()


#: Bytes that ``decoded`` adds up at once.
CHUNK = 1 << 16


def decoded(packets: list[tuple[str, bytes]]) -> list[bytes]:
    """Raw frames of (kind, bytes) in decode order, as ``decode`` gives them; runs of P packets are added up together."""
    out, at, before, last = [], 0, None, None
    while at < len(packets):
        kind, data = packets[at][0], zlib.decompress(packets[at][1])
        end, most = at + 1, max(1, CHUNK // max(1, len(data)))
        if kind == "B":
            out.append((np.frombuffer(data, np.uint8) + ((before.astype(np.int16) + last) >> 1).astype(np.uint8)).tobytes())
        else:
            while end < len(packets) and end - at < most and packets[end][0] == "P":
                end += 1
            run = np.frombuffer(data + b"".join([zlib.decompress(p[1]) for p in packets[at + 1 : end]]), np.uint8).reshape(end - at, -1)
            run = np.cumsum(run, 0, np.uint8) if kind == "I" else np.cumsum(run, 0, np.uint8) + last
            out += [r.tobytes() for r in run]
            before, last = run[-2] if len(run) > 1 else last, run[-1]
        at = end
    return out


def first_frames(packets: list[tuple[str, bytes]], n: int) -> Iterator[bytes]:
    """The first n raw frames in decode order, and no more: all at once where they are small, else as they are asked for."""
    if not n or not packets:
        return
    size = len(zlib.decompress(packets[0][1]))
    if size * min(n, len(packets)) <= CHUNK:
        yield from decoded(packets[:n])
    else:
        yield from (raw for _, raw in decode([{"kind": k, "bytes": b, "idx": 0} for k, b in packets[:n]]))


def in_display_order(packets: list[dict]) -> Iterator[tuple[int, bytes]]:
    """(index, raw frame) as a player shows them; only frames that wait for an earlier one are held."""
    order, held, shown = sorted(p["idx"] for p in packets), {}, 0
    for i, raw in decode(packets):
        held[i] = raw
        while shown < len(order) and order[shown] in held:
            yield order[shown], held.pop(order[shown])
            shown += 1
