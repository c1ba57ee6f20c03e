"""Rewrites of expressions, as folds on trees; Catalyst does the relational side.

* conversions that cancel are dropped only where no pixel depends on them (a round trip through
  three-byte pixels is lossy, so it goes only when nothing was drawn in between);
* identities, and whatever a later filled box or full paste hides entirely, are dropped.
"""

from __future__ import annotations

from reelspark.model.expr import Tree

_DRAWN = {"box", "corners", "text", "tint", "line", "circle", "mask"}


def elide_formats(t: Tree, fmt: str = "yuv420p") -> Tree:
    """pixfmt(pixfmt(x, other), fmt) -> x where x has ``fmt`` already; repeated conversions to one format -> one."""
    kids = [elide_formats(k, fmt) for k in t.kids]
    if t.op == "pixfmt":
        inner = kids[0]
        if inner.op == "pixfmt" and inner.text == t.text:
            return inner
        if t.text == fmt and inner.op == "pixfmt" and _native(inner.kids[0], fmt):
            return inner.kids[0]
        if t.text == fmt and _native(inner, fmt):
            return inner
    return Tree(t.op, kids, t.ints, t.text)


def _native(t: Tree, fmt: str) -> bool:
    return t.op == "ref" or (t.op == "pixfmt" and t.text == fmt)


def simplify(t: Tree, w: int, h: int) -> Tree:
    """Drops identities and draws that a filled box over the whole frame hides."""
    kids = [simplify(k, w, h) for k in t.kids]
    if t.op in ("identity", "copy"):
        return kids[0]
    if t.op == "box" and t.ints[7] < 0 and t.ints[0] <= 0 and t.ints[1] <= 0 and t.ints[2] >= w - 1 and t.ints[3] >= h - 1:
        base = kids[0]
        while base.op in _DRAWN:
            base = base.kids[0]
        kids = [base]
    return Tree(t.op, kids, t.ints, t.text)


def conversions(t: Tree) -> int:
    """Pixel format conversions of one frame."""
    return sum(n["op"] == "pixfmt" for n in t.flatten())
