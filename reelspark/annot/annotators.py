"""Higher-level drawing: one call per frame and its detections. The frames may be symbolic, which is all that
such a layer needs; each annotator composes the imaging calls and returns the frame."""

from __future__ import annotations

from collections.abc import Iterable, Mapping

from reelspark.lift.relational import ALPHA, REACH, WHITE
from reelspark.lift.shim import Imaging, SymFrame
from reelspark.sources.derive import COLORS

Detection = Mapping[str, object]


def color_of(d: Detection) -> tuple[int, int, int]:
    return COLORS.get(d["cls"], (255, 0, 0))


class Annotator:
    def __init__(self, imaging: Imaging):
        self.im = imaging

    def annotate(self, frame: SymFrame, dets: Iterable[Detection]) -> SymFrame:
        for d in dets:
            self.one(frame, d)
        return frame

    def one(self, frame: SymFrame, d: Detection) -> None:
        raise NotImplementedError


class Box(Annotator):
    def one(self, frame: SymFrame, d: Detection) -> None:
        self.im.box(frame, (d["x1"], d["y1"]), (d["x2"], d["y2"]), color_of(d), 1)


class BoxCorner(Annotator):
    def one(self, frame: SymFrame, d: Detection) -> None:
        self.im.corners(frame, (d["x1"], d["y1"]), (d["x2"], d["y2"]), color_of(d), REACH)


class Color(Annotator):
    def one(self, frame: SymFrame, d: Detection) -> None:
        self.im.tint(frame, (d["x1"], d["y1"]), (d["x2"], d["y2"]), color_of(d), ALPHA)


class Label(Annotator):
    """A filled tag at the box with the text on it."""

    def one(self, frame: SymFrame, d: Detection) -> None:
        x, y, s = d["x1"], d["y1"], d["text"]
        self.im.box(frame, (x, y), (x + 4 * len(s), y + 6), color_of(d), -1)
        self.im.text(frame, s, (x + 1, y + 1), WHITE, 1)


class Mask(Annotator):
    """Tints what the detection's mask, a frame of a one-channel clip, covers."""

    def __init__(self, imaging: Imaging, clip: str = "masks"):
        super().__init__(imaging)
        self.clip = imaging.open_clip(clip)

    def one(self, frame: SymFrame, d: Detection) -> None:
        self.clip.seek(d["mask_id"])
        ok, m = self.clip.read()
        if ok:
            self.im.mask(frame, m, color_of(d), ALPHA)


class Heat(Annotator):
    """Lays a raster over the frame; ``dets`` name rasters of a one-channel clip."""

    def __init__(self, imaging: Imaging, clip: str = "heat"):
        super().__init__(imaging)
        self.clip = imaging.open_clip(clip)

    def one(self, frame: SymFrame, d: Detection) -> None:
        self.clip.seek(d["raster"])
        ok, m = self.clip.read()
        if ok:
            self.im.heat(frame, m, ALPHA)


class Chain(Annotator):
    """Several annotators per detection, in order."""

    def __init__(self, imaging: Imaging, *parts: Annotator):
        super().__init__(imaging)
        self.parts = parts

    def one(self, frame: SymFrame, d: Detection) -> None:
        for p in self.parts:
            p.one(frame, d)
