"""Frame expressions as columns and as Python objects."""

from __future__ import annotations

from collections.abc import Sequence
from weakref import WeakValueDictionary

from pyspark.sql import Column
from pyspark.sql import functions as F


def node(op: str | Column, kids: Sequence[Column | int] = (), ints: Sequence[Column | int] = (), text: Column | str = "") -> Column:
    lit = lambda v: v if isinstance(v, Column) else F.lit(v)
    arr = lambda vs, kind: F.array(*[lit(v).cast(kind) for v in vs]) if vs else F.array().cast(f"array<{kind}>")
    # the types are those of NODE already; a cast would copy every node for the sake of what may be null
    return F.struct(lit(op).alias("op"), arr(kids, "int").alias("kids"), arr(ints, "bigint").alias("ints"), lit(text).alias("text"))


def ref(source: Column | str, idx: Column | int) -> Column:
    return node("ref", (), (idx,), source)


def canonical(nodes: Column) -> Column:
    """A text that is equal for equal expressions."""
    return F.array_join(F.transform(nodes, canonical_node), ";")


def canonical_node(n: Column) -> Column:
    return F.concat(n["op"], F.lit("("), F.array_join(n["kids"], ","), F.lit("|"), F.array_join(n["ints"], ","), F.lit("|"), n["text"], F.lit(")"))


def needs(nodes: Column) -> Column:
    """The set of (source, idx) that an expression refers to, sorted."""
    refs = F.filter(nodes, lambda n: n["op"] == "ref")
    return F.array_sort(F.array_distinct(F.transform(refs, lambda n: F.struct(n["text"].alias("source"), n["ints"][0].alias("idx")))))


class Tree:
    """An expression of a replayed script, hash-consed: equal sub-trees are one object, for as long as the script holds one."""

    __slots__ = ("op", "kids", "ints", "text", "size", "depth", "__weakref__")
    _known: WeakValueDictionary[tuple, Tree] = WeakValueDictionary()  # a tree holds its kids, so a key's ids stay theirs

    def __new__(cls, op: str, kids: Sequence[Tree] = (), ints: Sequence[int] = (), text: str = ""):
        key = (op, tuple(map(id, kids)), tuple(ints), text)
        found = cls._known.get(key)
        if found is None:
            found = object.__new__(cls)
            found.op, found.kids, found.ints, found.text = op, tuple(kids), tuple(int(i) for i in ints), text
            found.depth = 1 + max((k.depth for k in kids), default=0)
            cls._known[key] = found
        return found

    @classmethod
    def forget(cls) -> None:
        """Ends sharing with earlier scripts, which frees their trees."""
        cls._known.clear()

    def flatten(self) -> list[dict]:
        """Post-order node rows; a shared sub-tree stands once."""
        at: dict[int, int] = {}
        out: list[dict] = []
        stack: list[tuple[Tree, bool]] = [(self, False)]
        while stack:
            t, ready = stack.pop()
            if id(t) in at:
                continue
            if ready:
                at[id(t)] = len(out)
                out.append({"op": t.op, "kids": [at[id(k)] for k in t.kids], "ints": list(t.ints), "text": t.text})
            else:
                stack.append((t, True))
                stack += [(k, False) for k in reversed(t.kids)]
        return out

    @staticmethod
    def unflatten(nodes: Sequence[dict]) -> Tree:
        built: list[Tree] = []
        for n in nodes:
            built.append(Tree(n["op"], [built[k] for k in n["kids"]], n["ints"], n["text"]))
        return built[-1]
