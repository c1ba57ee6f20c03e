"""Pixel filters over NumPy arrays: pure, integer, exact.

A frame is (fmt, planes): planes are uint8 arrays in the order of the format. Every function returns a
new frame. ``apply_node`` evaluates one node of an expression, ``evaluate`` a whole one.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Callable

import numpy as np

from reelspark.engine.font import ADVANCE, HEIGHT, WIDTH, glyph

Frame = tuple[str, list[np.ndarray]]


def _clip(v: np.ndarray) -> np.ndarray:
    return np.maximum(np.minimum(v, 255), 0).astype(np.uint8)


#: What luma and chroma bytes add to 256 times a channel (b, g, r): luma with the rounding, u to b and g, v to g and r.
_BYTE = np.arange(256, dtype=np.int32)
_OF_LUMA = 298 * (_BYTE - 16) + 128
_OF_U, _OF_V = (np.array(k, np.int32)[:, None] * (_BYTE - 128) for k in ((516, -100, 0), (0, -208, 409)))


@functools.lru_cache(64)
def _cells(h: int, w: int, rows: int, cols: int) -> np.ndarray:
    """Which of ``rows`` x ``cols`` samples stands for each of h x w, as flat places."""
    out = _nearest(rows, h)[:, None] * cols + _nearest(cols, w)[None]
    out.setflags(write=False)
    return out


def yuv_to_bgr(planes: list[np.ndarray]) -> np.ndarray:
    """Integer BT.601 of limited range; chroma is repeated over its 2 x 2 block."""
    h, w = planes[0].shape
    if not h % 2 and not w % 2:
        u, v = planes[1:]
        chroma = _OF_U.take(u.reshape(-1), 1)
        chroma += _OF_V.take(v.reshape(-1), 1)
        out = chroma.take(_cells(h, w, h // 2, w // 2).reshape(-1), 1)
        out += _OF_LUMA.take(planes[0].reshape(-1))
        out >>= 8
        np.minimum(out, 255, out=out)
        np.maximum(out, 0, out=out)
        return out.T.astype(np.uint8, "C").reshape(h, w, 3)
    y = planes[0].astype(np.int32) - 16
    u, v = (np.repeat(np.repeat(p.astype(np.int32) - 128, 2, -2), 2, -1)[..., : y.shape[-2], : y.shape[-1]] for p in planes[1:])
    r = (298 * y + 409 * v + 128) >> 8
    g = (298 * y - 100 * u - 208 * v + 128) >> 8
    b = (298 * y + 516 * u + 128) >> 8
    return _clip(np.stack([b, g, r], -1))


#: Weights of b, g and r in luma, and in u and v. Sums stay below 2 ** 24, so single precision holds them exactly, and so it does parts by powers of two.
_LUMA, _CHROMA = np.array([25, 129, 66], np.float32), np.array([[112, -18], [-74, -94], [-38, 112]], np.float32)


def bgr_to_yuv(bgr: np.ndarray) -> list[np.ndarray]:
    """Luma per pixel; chroma from the sums of each 2 x 2 block, so one rounding per sample. An odd edge counts twice."""
    if not bgr.shape[0] % 2 and not bgr.shape[1] % 2:
        full = bgr.astype(np.float32)
        four = full[0::2] + full[1::2]
        four = four[:, 0::2] + four[:, 1::2]
        # weights leave no sample outside 16 .. 240, so nothing is clipped, and what is cut off is a positive rest
        y = full @ _LUMA
        y += 128 + 16 * 256
        y *= 1 / 256
        uv = four @ _CHROMA
        uv += 512 + 128 * 1024
        uv *= 1 / 1024
        uv = uv.astype(np.uint8)
        return [y.astype(np.uint8), np.ascontiguousarray(uv[..., 0]), np.ascontiguousarray(uv[..., 1])]
    b, g, r = (bgr[..., k].astype(np.int32) for k in range(3))
    y = ((66 * r + 129 * g + 25 * b + 128) >> 8) + 16
    if y.shape[0] % 2 or y.shape[1] % 2:
        b, g, r = (np.pad(x, ((0, x.shape[0] % 2), (0, x.shape[1] % 2)), "edge") for x in (b, g, r))
    b4, g4, r4 = (x[0::2, 0::2] + x[0::2, 1::2] + x[1::2, 0::2] + x[1::2, 1::2] for x in (b, g, r))
    u = ((-38 * r4 - 74 * g4 + 112 * b4 + 512) >> 10) + 128
    v = ((112 * r4 - 94 * g4 - 18 * b4 + 512) >> 10) + 128
    return [_clip(y), _clip(u), _clip(v)]


def pixfmt(frame: Frame, to: str) -> Frame:
    fmt, planes = frame
    if fmt == to:
        return frame
    if fmt == "rgb24":
        bgr = planes[0][..., ::-1]
    elif fmt == "bgr24":
        bgr = planes[0]
    elif fmt == "yuv420p":
        if to == "gray8":
            return to, [planes[0]]
        bgr = yuv_to_bgr(planes)
    else:
        bgr = np.repeat(planes[0][..., None], 3, -1)
    if to == "bgr24":
        return to, [np.ascontiguousarray(bgr)]
    if to == "rgb24":
        return to, [np.ascontiguousarray(bgr[..., ::-1])]
    out = bgr_to_yuv(bgr)
    return to, out if to == "yuv420p" else out[:1]


def _span(a: int, b: int, size: int) -> tuple[int, int]:
    return max(0, min(a, b)), min(size - 1, max(a, b))


def _edges(x1: int, y1: int, x2: int, y2: int, thick: int, reach: int | None, w: int, h: int) -> np.ndarray:
    """Pixels within the box and nearer than ``thick`` to its edge (all of it if thick < 0); with ``reach`` only near the corners."""
    x, y = np.arange(w)[None, :], np.arange(h)[:, None]
    inside = (x >= x1) & (x <= x2) & (y >= y1) & (y <= y2)
    if thick < 0:
        return inside
    mask = inside & ((x < x1 + thick) | (x > x2 - thick) | (y < y1 + thick) | (y > y2 - thick))
    if reach is not None:
        mask &= ((x < x1 + reach) | (x > x2 - reach)) & ((y < y1 + reach) | (y > y2 - reach))
    return mask


def _boxed(img: np.ndarray, x1: int, y1: int, x2: int, y2: int, thick: int, color: np.ndarray) -> np.ndarray:
    """Painted where ``_edges`` is set, by slices."""
    out = img.copy()
    left, right, top, bottom = max(0, x1), max(0, x2 + 1), max(0, y1), max(0, y2 + 1)
    if thick < 0:
        out[top:bottom, left:right] = color
        return out
    # what is near each edge, as far as it lies within the box
    out[top : min(bottom, max(top, y1 + thick)), left:right] = color
    out[max(top, y2 - thick + 1) : bottom, left:right] = color
    out[top:bottom, left : min(right, max(left, x1 + thick))] = color
    out[top:bottom, max(left, x2 - thick + 1) : right] = color
    return out


def _inside(img: np.ndarray, x1: int, y1: int, x2: int, y2: int) -> np.ndarray:
    """The part of a box that is seen, as a view."""
    return img[max(0, y1) : max(0, y2 + 1), max(0, x1) : max(0, x2 + 1)]


def _cornered(img: np.ndarray, x1: int, y1: int, x2: int, y2: int, reach: int, color: tuple[int, ...]) -> np.ndarray:
    """Painted where ``_edges`` with a reach is set, by slices."""
    out = img.copy()
    if reach > 0 and x1 <= x2 and y1 <= y2:
        for y in (y1, y2):
            _inside(out, x1, y, min(x2, x1 + reach - 1), y)[:] = color
            _inside(out, max(x1, x2 - reach + 1), y, x2, y)[:] = color
        for x in (x1, x2):
            _inside(out, x, y1, x, min(y2, y1 + reach - 1))[:] = color
            _inside(out, x, max(y1, y2 - reach + 1), x, y2)[:] = color
    return out


def _tinted(img: np.ndarray, x1: int, y1: int, x2: int, y2: int, color: tuple[int, ...], alpha: int) -> np.ndarray:
    """``blend`` over a whole box, by a slice."""
    out = img.copy()
    part = _inside(out, x1, y1, x2, y2)
    part[:] = _mixed(part, color, alpha)
    return out


def _lettered(img: np.ndarray, text: str, x: int, y: int, scale: int, color: tuple[int, ...]) -> np.ndarray:
    """Painted where ``text_mask`` is set, by the text's own dots."""
    out = img.copy()
    h, w = img.shape[:2]
    text = text[: _visible(x, scale, w)]
    if not text:
        return out
    dots = _strip(text, len(text))[:HEIGHT]
    if scale > 1:
        dots = dots.repeat(scale, 0).repeat(scale, 1)
    part = _inside(out, x, y, x + dots.shape[1] - 1, y + dots.shape[0] - 1)
    seen = dots[max(0, -y) :, max(0, -x) :][: part.shape[0], : part.shape[1]]
    np.copyto(part, np.asarray(color).astype(np.uint8), where=seen[..., None] if img.ndim == 3 else seen)
    return out


def _visible(x: int, scale: int, w: int) -> int:
    """How many characters of a text that begins at ``x`` can be seen."""
    return max(0, -(-(w - x) // (ADVANCE * scale))) if scale > 0 else 0


def paint(img: np.ndarray, mask: np.ndarray, color: tuple[int, ...]) -> np.ndarray:
    out = img.copy()
    out[mask] = color
    return out


def _mixed(img: np.ndarray, color: tuple[int, ...], alpha: int) -> np.ndarray:
    """(alpha * colour + (256 - alpha) * pixel) >> 8."""
    rest, share = _shares(color if img.ndim == 3 else color[:1], alpha)
    out = np.multiply(img, rest, dtype=share.dtype)
    out += share
    out >>= 8
    return out


@functools.lru_cache(1024)
def _shares(color: tuple[int, ...], alpha: int) -> tuple[np.generic, np.ndarray]:
    """(256 - alpha, alpha * colour), in two bytes where a sum of 256 * 255 is the most."""
    kind = np.uint16 if 0 <= alpha <= 256 and all(0 <= c < 256 for c in color) else np.int32
    return kind(256 - alpha), (alpha * np.array(color, np.int64)).astype(kind)


def blend(img: np.ndarray, mask: np.ndarray, color: tuple[int, ...], alpha: int) -> np.ndarray:
    """(alpha * colour + (256 - alpha) * pixel) >> 8 where the mask is set."""
    out = img.copy()
    np.copyto(out, _mixed(img, color, alpha), where=mask[..., None] if img.ndim == 3 else mask, casting="unsafe")
    return out


def _image(frame: Frame) -> np.ndarray:
    if frame[0] not in ("bgr24", "rgb24", "gray8"):
        raise TypeError(f"a drawing filter can't take {frame[0]}")
    return frame[1][0]


def _each_plane(frame: Frame, f: Callable[[np.ndarray, int, int], np.ndarray]) -> Frame:
    from reelspark.model.schemas import FORMATS

    return frame[0], [f(p, a, b) for p, (a, b, _) in zip(frame[1], FORMATS[frame[0]], strict=True)]


def _resize(p: np.ndarray, w: int, h: int, mode: int) -> np.ndarray:
    if mode == 1:  # 2 x 2 box: exact halving
        s = p.astype(np.int32)
        return ((s[0::2, 0::2] + s[0::2, 1::2] + s[1::2, 0::2] + s[1::2, 1::2] + 2) >> 2).astype(np.uint8)
    if p.ndim == 2:
        return p.reshape(-1).take(_cells(h, w, *p.shape))
    return p[_nearest(p.shape[0], h)][:, _nearest(p.shape[1], w)]


@functools.lru_cache(64)
def _nearest(n: int, to: int) -> np.ndarray:
    """Which of n samples stands for each of ``to``."""
    out = np.arange(to) * n // to
    out.setflags(write=False)
    return out


def heat_color(v: np.ndarray) -> np.ndarray:
    """Blue to red over green, by integer ramps."""
    v = v.astype(np.int32)
    return np.stack([_clip(255 - 2 * v), _clip(255 - np.abs(2 * v - 255)), _clip(2 * v - 255)], -1)


class Canvas:
    """A small picture that is drawn on: opaque drawings wait as sets of pixels, an integer with a bit a pixel each, the last on top."""

    MOST = 4096  # pixels; larger pictures are drawn on at once

    def __init__(self, img: np.ndarray, layers: tuple = ()):
        self.img, self.layers = img, layers

    def drawn(self, op: str, ints: list[int], text: str) -> Canvas | None:
        """With one drawing more; None: not one that can wait."""
        h, w = self.img.shape[:2]
        if op == "box":
            x1, y1, x2, y2, *color, thick = ints
            bits = _area(x1, y1, x2, y2, w, h)
            if thick >= 0:
                bits &= ~_area(x1 + thick, y1 + thick, x2 - thick, y2 - thick, w, h)
        elif op == "corners":
            x1, y1, x2, y2, *color, reach = ints
            bits = _area(x1, y1, x2, y2, w, h) & ~(_area(x1 + 1, y1 + 1, x2 - 1, y2 - 1, w, h) | _area(x1 + reach, y1, x2 - reach, y2, w, h) | _area(x1, y1 + reach, x2, y2 - reach, w, h))
        elif op == "text" and ints[0] >= 0 and ints[1] >= 0 and ints[5] == 1:
            x, y, *color, _ = ints
            bits = _dots(text[: _visible(x, 1, w)], max(0, w - x), w) << (y * w + x) & (1 << w * h) - 1 if x < w and y < h else 0
        else:
            return None
        return Canvas(self.img, (*self.layers, (bits, tuple(color))))

    def flat(self) -> np.ndarray:
        """The picture with what waits painted."""
        if not self.layers:
            return self.img
        left, seen = (1 << self.img.shape[0] * self.img.shape[1]) - 1, {}
        for bits, color in reversed(self.layers):
            if bits := bits & left:
                left ^= bits
                seen[color] = seen.get(color, 0) | bits
        h, w = self.img.shape[:2]
        size, out = -(-h * w // 8), self.img.copy()
        if seen:
            where = np.unpackbits(np.frombuffer(b"".join([b.to_bytes(size, "little") for b in seen.values()]), np.uint8).reshape(len(seen), size), 1, h * w, "little").view(bool)
            for color, mask in zip(seen, where.reshape(-1, h, w, 1), strict=True):
                np.copyto(out, _paint_of(color), where=mask)
        return out


@functools.lru_cache(256)
def _rows(n: int, w: int) -> int:
    """The first pixel of each of n rows."""
    return sum(1 << w * k for k in range(n))


def _area(x1: int, y1: int, x2: int, y2: int, w: int, h: int) -> int:
    """The pixels of a box, both ends included."""
    x1, y1, x2, y2 = x1 if x1 > 0 else 0, y1 if y1 > 0 else 0, x2 if x2 < w else w - 1, y2 if y2 < h else h - 1
    return 0 if x1 > x2 or y1 > y2 else _rows(y2 - y1 + 1, w) * ((1 << x2 + 1) - (1 << x1)) << y1 * w


@functools.lru_cache(4096)
def _dots(text: str, seen: int, w: int) -> int:
    """A text's dots at scale 1 in rows of w pixels, its first ``seen`` columns."""
    return sum(int(dot) << r * w + c for r, row in enumerate(_strip(text, len(text))[:HEIGHT, :seen].tolist()) for c, dot in enumerate(row)) if text else 0


def canvas(frame: Frame) -> Frame:
    """A frame of three-byte pixels to draw on, if it is small."""
    img = _image(frame)
    return (frame[0], [Canvas(img)]) if img.ndim == 3 and img.shape[0] * img.shape[1] <= Canvas.MOST else frame


def painted(frame: Frame) -> Frame:
    """A frame without drawings that wait."""
    return (frame[0], [frame[1][0].flat()]) if type(frame[1][0]) is Canvas else frame


def apply_node(op: str, kids: list[Frame], ints: list[int], text: str) -> Frame:
    first = kids[0]
    if type(first[1][0]) is Canvas:
        more = first[1][0].drawn(op, ints, text)
        if more is not None:
            return first[0], [more]
        return apply_node(op, [painted(k) for k in kids], ints, text)
    if op == "pixfmt":
        return pixfmt(first, text)
    if op in ("identity", "copy"):
        return first
    if op in ("box", "corners", "text", "tint", "line", "circle"):
        img = _image(first)
        h, w = img.shape[:2]
        if op == "box":
            return first[0], [_boxed(img, *ints[:4], ints[7], _paint_of(_color(img, tuple(ints[4:7]))))]
        if op == "corners":
            return first[0], [_cornered(img, *ints[:4], ints[7], _paint_of(_color(img, tuple(ints[4:7]))))]
        if op == "text":
            return first[0], [_lettered(img, text, *ints[:2], ints[5], _paint_of(_color(img, tuple(ints[2:5]))))]
        if op == "tint":
            return first[0], [_tinted(img, *ints[:4], _color(img, tuple(ints[4:7])), ints[7])]
        if op == "line":
            x1, y1, x2, y2, b, g, r = ints
            n = max(abs(x2 - x1), abs(y2 - y1), 1)
            t = np.arange(n + 1)
            xs, ys = x1 + (2 * (x2 - x1) * t + n) // (2 * n), y1 + (2 * (y2 - y1) * t + n) // (2 * n)
            ok = (xs >= 0) & (xs < w) & (ys >= 0) & (ys < h)
            mask = np.zeros((h, w), bool)
            mask[ys[ok], xs[ok]] = True
        else:
            cx, cy, radius, b, g, r = ints
            x, y = np.arange(w)[None, :], np.arange(h)[:, None]
            d = (x - cx) ** 2 + (y - cy) ** 2
            mask = (d <= radius * radius) & (d > (radius - 1) * (radius - 1))
        return first[0], [paint(img, mask, _color(img, (b, g, r)))]
    if op == "mask":
        img, m = _image(first), kids[1][1][0]
        b, g, r, alpha = ints
        h, w = img.shape[:2]
        return first[0], [blend(img, _resize(m, w, h, 0) > 0, _color(img, (b, g, r)), alpha)]
    if op == "heat":
        img, m = _image(first), kids[1][1][0]
        h, w = img.shape[:2]
        alpha = ints[0]
        return first[0], [((alpha * heat_color(_resize(m, w, h, 0)).astype(np.int32) + (256 - alpha) * img.astype(np.int32)) >> 8).astype(np.uint8)]
    if op == "grid":
        cols = ints[0]
        rows = -(-len(kids) // cols)
        out = []
        for p in range(len(first[1])):
            cell = first[1][p]
            blank = np.zeros_like(cell)
            cells = [k[1][p] for k in kids] + [blank] * (rows * cols - len(kids))
            out.append(np.concatenate([np.concatenate(cells[r * cols : (r + 1) * cols], 1) for r in range(rows)], 0))
        return first[0], out
    if op == "resize":
        w, h, mode = ints
        return _each_plane(first, lambda p, a, b: _resize(p, w // a, h // b, mode))
    if op == "crop":
        x, y, w, h = ints
        return _each_plane(first, lambda p, a, b: p[y // b : (y + h) // b, x // a : (x + w) // a].copy())
    if op == "paste":
        x, y = ints
        out = [p.copy() for p in first[1]]
        for p, q in zip(out, kids[1][1], strict=True):
            p[y : y + q.shape[0], x : x + q.shape[1]] = q[: p.shape[0] - y, : p.shape[1] - x]
        return first[0], out
    if op == "flip":
        return _each_plane(first, lambda p, a, b: np.ascontiguousarray(p[:, ::-1] if ints[0] else p[::-1]))
    if op == "blend":
        a = ints[0]
        return first[0], [((a * q.astype(np.int32) + (256 - a) * p.astype(np.int32)) >> 8).astype(np.uint8) for p, q in zip(first[1], kids[1][1], strict=True)]
    if op == "gray":
        return pixfmt(pixfmt(first, "gray8"), first[0])
    raise KeyError(op)


def _color(img: np.ndarray, bgr: tuple[int, int, int]) -> tuple[int, ...]:
    return bgr if img.ndim == 3 else (((66 * bgr[2] + 129 * bgr[1] + 25 * bgr[0] + 128) >> 8) + 16,)


@functools.lru_cache(1024)
def _paint_of(color: tuple[int, ...]) -> np.ndarray:
    """A colour as the bytes that a picture takes."""
    out = np.array(color).astype(np.uint8)
    out.setflags(write=False)
    return out


def evaluate(nodes: list[tuple[str, list[int], list[int], str]], fetch: Callable[[str, int], Frame]) -> Frame:
    """Evaluates a post-order list; equal sub-trees stand there once, so each is computed once."""
    values: list[Frame] = []
    for op, kids, ints, text in nodes:
        values.append(fetch(text, ints[0]) if op == "ref" else apply_node(op, [values[k] for k in kids], ints, text))
    return values[-1]


class Forest:
    """Expressions of many generations as columns: node rows end to end, no Python object a node."""

    def __init__(self, nodes):
        """``nodes``: an Arrow list of node structs a row."""
        import pyarrow as pa
        import pyarrow.compute as pc

        if isinstance(nodes, pa.ChunkedArray):
            nodes = nodes.combine_chunks() if nodes.num_chunks != 1 else nodes.chunk(0)

        def ends(lists):
            return np.concatenate([[0], np.cumsum(pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False))]).astype(np.int64)

        def coded(values):
            d = values.dictionary_encode()
            return d.indices.to_numpy(zero_copy_only=False), d.dictionary.to_pylist()

        flat = nodes.flatten()
        op, kids, ints, text = flat.flatten()
        self.at, self.n = ends(nodes), len(nodes)
        (self.op, self.ops), (self.text, self.texts) = coded(op), coded(text)
        self.kids_at, self.kids = ends(kids), kids.flatten().to_numpy(zero_copy_only=False)
        self.ints_at, self.ints = ends(ints), ints.flatten().to_numpy(zero_copy_only=False)
        # what makes two expressions one form: operations, kids, formats and sources
        plain = np.isin(self.op, [k for k, o in enumerate(self.ops) if o in ("ref", "pixfmt")])
        self.form = np.stack([self.op, np.diff(self.kids_at), np.diff(self.ints_at), np.where(plain, self.text, -1)], 1).astype(np.int64)

    def forms(self, rows) -> dict[tuple[bytes, bytes], list[int]]:
        """Rows by form."""
        out: dict[tuple[bytes, bytes], list[int]] = {}
        at, kids_at = self.at.tolist(), self.kids_at
        for r in rows:
            a, b = at[r], at[r + 1]
            out.setdefault((self.form[a:b].tobytes(), self.kids[kids_at[a] : kids_at[b]].tobytes()), []).append(r)
        return out

    def needs(self) -> list[list[tuple[str, int]]]:
        """(source, idx) of the references of every row, as they stand."""
        out: list[list[tuple[str, int]]] = [[] for _ in range(self.n)]
        refs = np.flatnonzero(np.isin(self.op, [k for k, o in enumerate(self.ops) if o == "ref"]))
        rows = np.searchsorted(self.at, refs, "right") - 1
        for r, t, i in zip(rows.tolist(), self.text[refs].tolist(), self.ints[self.ints_at[refs]].tolist(), strict=True):
            out[r].append((self.texts[t], i))
        return out

    def nodes(self, row: int) -> list[tuple]:
        return [(self.ops[self.op[j]], self.kids[self.kids_at[j] : self.kids_at[j + 1]].tolist(), self.ints[self.ints_at[j] : self.ints_at[j + 1]].tolist(), self.texts[self.text[j]]) for j in range(self.at[row], self.at[row + 1])]


def _masks(texts: list[str], codes: np.ndarray, ints: np.ndarray, w: int, h: int) -> np.ndarray:
    """``text_mask`` of many generations: one strip a distinct text, put where each stands."""
    x, y, scale = ints[:, 0], ints[:, 1], int(ints[0, 5])
    known, which = np.unique(codes, return_inverse=True)
    most = _visible(int(x.min()), scale, w)
    longest = min(most, max(len(texts[k]) for k in known))
    strips = np.stack([_strip(texts[k][:longest], longest) for k in known])
    px, py = (np.arange(w)[None] - x[:, None]) // scale, (np.arange(h)[None] - y[:, None]) // scale
    px[(px < 0) | (px >= longest * ADVANCE)] = longest * ADVANCE
    py[(py < 0) | (py >= HEIGHT)] = HEIGHT
    rows, width = (which[:, None] * (HEIGHT + 1) + py) * strips.shape[2], px[:, None, :]
    return strips.reshape(-1).take(rows[:, :, None] + width)


@functools.lru_cache(4096)
def _strip(text: str, longest: int) -> np.ndarray:
    """A text's dots at scale 1; the last row and column stay empty."""
    strip = np.zeros((HEIGHT + 1, longest * ADVANCE + 1), bool)
    for c, ch in enumerate(text):
        strip[:HEIGHT, c * ADVANCE : c * ADVANCE + WIDTH] = np.array([d == "1" for d in glyph(ch)]).reshape(HEIGHT, WIDTH)
    strip.setflags(write=False)
    return strip


def _areas(op: str, ints: np.ndarray, w: int, h: int) -> np.ndarray:
    """``_edges`` of many generations."""
    x1, y1, x2, y2 = (ints[:, k, None] for k in range(4))
    x, y = np.arange(w)[None], np.arange(h)[None]
    inside_x, inside_y = (x >= x1) & (x <= x2), (y >= y1) & (y <= y2)
    inside = inside_y[:, :, None] & inside_x[:, None, :]
    last = ints[:, 7, None]
    if op == "tint" or op == "box" and (last < 0).all():
        return inside
    thick = np.ones_like(last) if op == "corners" else last
    edge = ((x < x1 + thick) | (x > x2 - thick))[:, None, :] | ((y < y1 + thick) | (y > y2 - thick))[:, :, None]
    if op == "corners":
        return inside & edge & ((x < x1 + last) | (x > x2 - last))[:, None, :] & ((y < y1 + last) | (y > y2 - last))[:, :, None]
    return inside & (edge | (last < 0)[:, :, None])


def _painted(img: np.ndarray, mask: np.ndarray, color: np.ndarray) -> np.ndarray:
    """``img``: (n, channel, h, w); bits of the colour where the mask is set."""
    bits = np.negative(mask.view(np.uint8))[:, None]
    return img ^ ((img ^ color.astype(np.uint8)[:, :, None, None]) & bits)


def _blended(img: np.ndarray, mask: np.ndarray, color: np.ndarray, alpha: np.ndarray) -> np.ndarray:
    kind = np.uint16 if ((alpha >= 0) & (alpha <= 256)).all() else np.int64  # what is at most 256 * 255 fits two bytes
    mixed = img * (256 - alpha).astype(kind)[:, None, None, None]
    mixed += (alpha[:, None] * color).astype(kind)[:, :, None, None]
    mixed >>= kind(8)
    out = mixed.astype(np.uint8)
    out ^= img
    out &= np.negative(mask.view(np.uint8))[:, None]
    out ^= img
    return out


class _Layers:
    """Small pictures of many generations that are drawn on: opaque drawings wait, the last on top, and become rows of bits together."""

    MOST = 64  # pixels a row

    def __init__(self, img: np.ndarray, layers: tuple = ()):
        self.img, self.layers, self.shape, self.ndim = img, layers, img.shape, img.ndim

    def drawn(self, op: str, ints: np.ndarray, texts: list[str], codes: np.ndarray) -> _Layers | None:
        """With one drawing more; None: not one that can wait."""
        if op == "text" and ((ints[:, 5] != 1).any() or self.shape[3] - int(ints[:, 0].min()) > 64 - ADVANCE):
            return None
        return _Layers(self.img, (*self.layers, (op, ints, texts, codes)))

    def flat(self) -> np.ndarray:
        if not self.layers:
            return self.img
        n, _, h, w = self.img.shape
        rows, colors = np.empty((len(self.layers), n, h), _row_type(w)), np.empty((len(self.layers), n), np.int64)
        for op in ("box", "corners", "text"):
            mine = [k for k, layer in enumerate(self.layers) if layer[0] == op]
            if mine:
                ints = np.concatenate([self.layers[k][1] for k in mine])
                one = _text_rows(self.layers[mine[0]][2], np.concatenate([self.layers[k][3] for k in mine]), ints, w, h) if op == "text" else _area_rows(op, ints, w, h)
                rows[mine] = one.reshape(len(mine), n, h)
                c = ints[:, 2:5] if op == "text" else ints[:, 4:7]
                colors[mine] = (c[:, 0] | c[:, 1] << 8 | c[:, 2] << 16).reshape(len(mine), n)
        known = np.unique(colors)
        if len(known) > 16:
            out = self.img
            for one, c in zip(rows, colors, strict=True):
                out = _painted(out, _unpacked(one, w).view(bool), c[:, None] >> np.array([0, 8, 16]) & 255)
            return out
        covered = np.bitwise_or.accumulate(rows[::-1], 0)[::-1]  # by a drawing or those above it
        rows[:-1] &= ~covered[1:]
        out = self.img & (_unpacked(covered[0], w) - np.uint8(1))[:, None]
        for one in known.tolist():
            dots = _unpacked(np.bitwise_or.reduce(rows * (colors == one)[:, :, None], 0), w)
            for ch in range(3):
                if value := one >> 8 * ch & 255:
                    out[:, ch] |= dots * np.uint8(value)
        return out


def _row_type(w: int) -> type:
    return np.uint16 if w <= 16 else np.uint32 if w <= 32 else np.uint64


def _unpacked(rows: np.ndarray, w: int) -> np.ndarray:
    """Rows of bits as bytes 0 and 1."""
    return np.unpackbits(rows.astype(rows.dtype.newbyteorder("<"), copy=False).view(np.uint8).reshape(*rows.shape, rows.dtype.itemsize), -1, w, "little")


@functools.lru_cache(64)
def _ones(w: int) -> np.ndarray:
    """0 to w bits set."""
    return np.array([(1 << k) - 1 for k in range(w + 1)], np.uint64)


def _span_bits(a: np.ndarray, b: np.ndarray, w: int) -> np.ndarray:
    """Bits a to b of a row, both included."""
    ones = _ones(w)
    return ones[np.clip(b + 1, 0, w)] & ~ones[np.clip(a, 0, w)]


def _area_rows(op: str, ints: np.ndarray, w: int, h: int) -> np.ndarray:
    """``_areas`` of boxes and corners as rows of bits."""
    x1, y1, x2, y2, last = (ints[:, k] for k in (0, 1, 2, 3, 7))
    y, kind = np.arange(h)[None], _row_type(w)
    inside = (y >= y1[:, None]) & (y <= y2[:, None])
    full = _span_bits(x1, x2, w)
    if op == "tint" or op == "box" and (last < 0).all():
        return full.astype(kind)[:, None] * inside
    thick = np.ones_like(last) if op == "corners" else last
    edge = (y < (y1 + thick)[:, None]) | (y > (y2 - thick)[:, None])
    if op == "box":
        edge |= (last < 0)[:, None]
    sides = full & ~_span_bits(x1 + thick, x2 - thick, w)
    if op == "corners":
        near = ~_span_bits(x1 + last, x2 - last, w)
        full, sides = full & near, sides & near
        inside &= (y < (y1 + last)[:, None]) | (y > (y2 - last)[:, None])
    return np.where(edge, full.astype(kind)[:, None], sides.astype(kind)[:, None]) * inside


def _text_rows(texts: list[str], codes: np.ndarray, ints: np.ndarray, w: int, h: int) -> np.ndarray:
    """``_masks`` at scale 1 as rows of bits, where what may be seen of a text is no longer than a row's type."""
    x, y = ints[:, 0], ints[:, 1]
    known, which = np.unique(codes, return_inverse=True)
    longest = min(_visible(int(x.min()), 1, w), max(len(texts[k]) for k in known))
    dots = np.array([_strip_rows(texts[k][:longest]) for k in known], np.uint64)[which]
    by = x[:, None]
    dots = np.where(by >= 0, dots << np.clip(by, 0, 63).astype(np.uint64), dots >> np.clip(-by, 0, 63).astype(np.uint64))
    dots = np.where((by < w) & (by > -64), dots, np.uint64(0)) & _ones(w)[w]
    at = np.arange(h)[None] - y[:, None]
    at[(at < 0) | (at >= HEIGHT)] = HEIGHT
    return np.take_along_axis(dots.astype(_row_type(w)), at, 1)


@functools.lru_cache(4096)
def _strip_rows(text: str) -> tuple[int, ...]:
    """A text's dots at scale 1, a number a row; the last row is empty."""
    return tuple(sum(int(dot) << c for c, dot in enumerate(row)) for row in _strip(text, len(text)).tolist())


def _flat(frames: Frame) -> Frame:
    return (frames[0], [frames[1][0].flat()]) if type(frames[1][0]) is _Layers else frames


def _many_bgr(planes: list[np.ndarray]) -> np.ndarray:
    (n, h, w), (u, v) = planes[0].shape, (p.astype(np.int32) - 128 for p in planes[1:])
    y = 298 * planes[0].astype(np.int32) + (128 - 298 * 16)
    out = np.empty((n, 3, h, w), np.uint8)
    for k, chroma in enumerate((516 * u, -100 * u - 208 * v, 409 * v)):
        one = np.repeat(chroma, 2, -1)[..., :w].repeat(2, -2)[:, :h]
        one += y
        one >>= 8
        np.minimum(one, 255, out=one)
        np.maximum(one, 0, out=one)
        out[:, k] = one
    return out


def _many_yuv(bgr: np.ndarray) -> list[np.ndarray]:
    # luma's sum is at most 220 * 255 + 128, a block's of four bytes 1,020
    b, g, r = (bgr[:, k].astype(np.uint16) for k in range(3))
    y = ((66 * r + 129 * g + 25 * b + 128) >> 8) + 16
    odd = y.shape[1] % 2, y.shape[2] % 2
    if any(odd):
        b, g, r = (np.pad(x, ((0, 0), (0, odd[0]), (0, odd[1])), "edge") for x in (b, g, r))
    rows = (x[:, 0::2] + x[:, 1::2] for x in (b, g, r))
    b4, g4, r4 = ((x[:, :, 0::2] + x[:, :, 1::2]).astype(np.int32) for x in rows)
    # weights leave no sample outside 16 .. 240, so nothing is clipped
    u = ((-38 * r4 - 74 * g4 + 112 * b4 + 512) >> 10) + 128
    v = ((112 * r4 - 94 * g4 - 18 * b4 + 512) >> 10) + 128
    return [y.astype(np.uint8), u.astype(np.uint8), v.astype(np.uint8)]


def _apply_many(op: str, kids: list[Frame], ints: np.ndarray, texts: list[str], codes: np.ndarray) -> Frame:
    """A node of many generations whose kids have equal formats and sizes; planes have the generation in front, and three-byte pixels
    stand as three planes in one array. Operations that have no form of their own are applied one by one."""
    fmt, planes = kids[0]
    if op in ("identity", "copy"):
        return kids[0]
    if op == "pixfmt":
        kids = [_flat(kids[0])]
        fmt, planes = kids[0]
        to = texts[codes[0]]
        if fmt == to:
            return kids[0]
        if (fmt, to) == ("yuv420p", "bgr24"):
            return to, [_many_bgr(planes)]
        if (fmt, to) == ("bgr24", "yuv420p"):
            return to, _many_yuv(planes[0])
    elif fmt == "bgr24" and _bytes(op, ints):
        if op in ("box", "corners", "text") and planes[0].shape[3] <= _Layers.MOST:
            below = planes[0] if type(planes[0]) is _Layers else _Layers(planes[0])
            more = below.drawn(op, ints, texts, codes)
            if more is not None:
                return fmt, [more]
        kids = [_flat(k) for k in kids]
        (img,), (h, w) = kids[0][1], planes[0].shape[2:]
        if op in ("box", "corners"):
            return fmt, [_painted(img, _areas(op, ints, w, h), ints[:, 4:7])]
        if op == "text" and len(set(ints[:, 5].tolist())) == 1 and ints[0, 5] > 0:
            return fmt, [_painted(img, _masks(texts, codes, ints, w, h), ints[:, 2:5])]
        if op == "tint":
            area = _unpacked(_area_rows(op, ints, w, h), w).view(bool) if w <= _Layers.MOST else _areas(op, ints, w, h)
            return fmt, [_blended(img, area, ints[:, 4:7], ints[:, 7])]
        if op == "mask":
            m = kids[1][1][0]
            m = (m > 0).reshape(len(m), -1).take(_cells(h, w, *m.shape[1:]), 1)
            return fmt, [_blended(img, m, ints[:, :3], ints[:, 3])]
    kids = [_flat(k) for k in kids]
    out = [apply_node(op, [single(k, i) for k in kids], ints[i].tolist(), texts[codes[i]]) for i in range(len(codes))]
    return _stacked(out)


def _bytes(op: str, ints: np.ndarray) -> bool:
    """Whether a drawing's colours fit a byte."""
    c = ints[:, {"text": 2, "mask": 0}.get(op, 4) :][:, :3]
    return not (c >> 8).any()


#: Operations whose result is as large as their first kid, so that many generations stay one array.
_SAME_SIZE = {"ref", "identity", "copy", "pixfmt", "box", "corners", "text", "tint", "mask"}


def _stacked(frames: list[Frame]) -> Frame:
    return frames[0][0], [np.stack([np.moveaxis(p, -1, 0) if p.ndim == 3 else p for p in ps]) for ps in zip(*(f[1] for f in frames), strict=True)]


def single(frames: Frame, i: int) -> Frame:
    """One of many frames, as the other functions take it."""
    return frames[0], [np.ascontiguousarray(np.moveaxis(p[i], 0, -1)) if p.ndim == 4 else p[i] for p in frames[1]]


def evaluate_many(forest: Forest, rows: list[int], fetch: Callable[[int, str, int], tuple[bytes, int, int, str]]) -> list[tuple[int, int, str, bytes]]:
    """``evaluate`` of many rows, by form: (w, h, fmt, raw) for each of ``rows``. ``fetch(row, source, idx)``: (raw, w, h, fmt)."""
    place, out = {r: k for k, r in enumerate(rows)}, [None] * len(rows)
    for group in forest.forms(rows).values():
        first, where = forest.at[group[0]], forest.at[np.array(group)]
        inputs = []
        refs = [j for j in range(forest.at[group[0] + 1] - first) if forest.ops[forest.op[first + j]] == "ref"]
        for j in refs:
            source = forest.texts[forest.text[first + j]]
            inputs.append([fetch(r, source, i) for r, i in zip(group, forest.ints[forest.ints_at[where + j]].tolist(), strict=True)])
        sizes: dict[tuple, list[int]] = {}
        for k in range(len(group)):
            sizes.setdefault(tuple([one[k][1:] for one in inputs]), []).append(k)
        if not {forest.ops[k] for k in forest.op[first : forest.at[group[0] + 1]].tolist()} <= _SAME_SIZE:
            for k, r in enumerate(group):
                have = {(forest.texts[forest.text[where[k] + j]], int(forest.ints[forest.ints_at[where[k] + j]])): from_raw(*one[k]) for j, one in zip(refs, inputs, strict=True)}
                frame = evaluate(forest.nodes(r), lambda s, i, have=have: have[s, i])
                out[place[r]] = (*size_of(frame), frame[0], raw(frame))
            continue
        for shape, members in sizes.items():  # sources of one name have one size, so this is one part
            for k, done in zip(members, _form(forest, where[members], int(forest.at[group[0] + 1] - first), {j: [one[k][0] for k in members] for j, one in zip(refs, inputs, strict=True)}, dict(zip(refs, shape, strict=True))), strict=True):
                out[place[group[k]]] = done
    return out


def _form(forest: Forest, where: np.ndarray, size: int, raws: dict[int, list[bytes]], shape: dict[int, tuple[int, int, str]]) -> list[tuple[int, int, str, bytes]]:
    first, values, left = int(where[0]), [], {}
    kids_of = [forest.kids[forest.kids_at[first + j] : forest.kids_at[first + j + 1]].tolist() for j in range(size)]
    for j, kids in enumerate(kids_of):
        for k in kids:
            left[k] = j
    for j in range(size):
        op = forest.ops[forest.op[first + j]]
        if op == "ref":
            w, h, fmt = shape[j]
            flat = np.frombuffer(b"".join(raws[j]), np.uint8).reshape(len(where), -1)
            values.append(_stacked([from_raw(bytes(r), w, h, fmt) for r in raws[j]]) if fmt in ("bgr24", "rgb24") else _split(flat, w, h, fmt))
        else:
            n = int(forest.ints_at[first + j + 1] - forest.ints_at[first + j])
            ints = forest.ints[forest.ints_at[where + j][:, None] + np.arange(n)[None]]
            values.append(_apply_many(op, [values[k] for k in kids_of[j]], ints, forest.texts, forest.text[where + j]))
        for k in kids_of[j]:
            if left[k] == j and k != size - 1:
                values[k] = None
    fmt, planes = _flat(values[-1])
    h, w = planes[0].shape[-2:]
    if planes[0].ndim == 4:
        planes = [np.moveaxis(planes[0], 1, -1)]
    data = np.concatenate([np.ascontiguousarray(p).reshape(len(where), -1) for p in planes], 1)
    return [(w, h, fmt, d.tobytes()) for d in data]


def _split(flat: np.ndarray, w: int, h: int, fmt: str) -> Frame:
    from reelspark.model.schemas import FORMATS

    out, at = [], 0
    for a, b, _ in FORMATS[fmt]:
        rows, cols = -(-h // b), -(-w // a)
        out.append(flat[:, at : at + rows * cols].reshape(-1, rows, cols))
        at += rows * cols
    return fmt, out


def raw(frame: Frame) -> bytes:
    return b"".join(p.tobytes() for p in frame[1])


def from_raw(data: bytes, w: int, h: int, fmt: str) -> Frame:
    from reelspark.model.schemas import FORMATS

    out, at, flat = [], 0, np.frombuffer(data, np.uint8)
    for a, b, c in FORMATS[fmt]:
        rows, cols = -(-h // b), -(-w // a)
        n = rows * cols * c
        out.append(flat[at : at + n].reshape((rows, cols, c) if c > 1 else (rows, cols)))
        at += n
    return fmt, out


def digest(frame: Frame) -> str:
    """md5 of the comma-joined bytes of all planes in order, which SQL can compute as well."""
    return hashlib.md5(",".join(map(str, raw(frame))).encode()).hexdigest()


#: Every byte's decimal and a comma, padded to four characters.
_DECIMALS = np.frombuffer(b"".join(f"{i},".encode().ljust(4) for i in range(256)), np.uint32)


def digests(raws: list[bytes], at_once: int = 1 << 20) -> list[str]:
    """``digest`` of the raw bytes of many frames; a frame at a time where frames are large."""
    out, k = [], 0
    while k < len(raws):
        size, lo = 0, k
        while k < len(raws) and (k == lo or size + len(raws[k]) <= at_once):
            size, k = size + len(raws[k]), k + 1
        text, at = _DECIMALS[np.frombuffer(b"".join(raws[lo:k]), np.uint8)].tobytes(), 0
        for r in raws[lo:k]:
            end = at + 4 * len(r)
            out.append(hashlib.md5(text[at:end].translate(None, b" ")[:-1]).hexdigest())
            at = end
    return out


def size_of(frame: Frame) -> tuple[int, int]:
    return frame[1][0].shape[1], frame[1][0].shape[0]
