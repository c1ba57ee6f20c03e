"""Edit-aware token counts: a tree over each document's pieces (the tokenizer pattern's matches).

A leaf holds a run of pieces with their lengths and token counts; inner nodes hold sums. An edit
replaces a span of characters: only the pieces it touches are split and encoded anew, beginning with
enough context before the span for the pattern's look-ahead and ending where the new pieces fall in step
with old ones; their leaves are replaced and the sums on the paths above them are renewed.

The trees are kept: ``build`` gives a table with one row a document (text, version, counts, and the tree's leaves packed, two
small numbers a piece), which is written once; ``apply_edits`` takes that table and a table of edits, passes documents without
edits on untouched (no Python, no shuffle of them if the edits are few), raises the trees of the others from their leaves without encoding
anything, edits them, and gives the new table. Only regions around edits are encoded, ever again.

Context before an edit: a match depends only on the text from its start on, and looks ahead over a whole run
of white space plus ``AHEAD`` characters, so pieces ending before that are safe. After the edit, the first old
boundary that is met again ends the work, because equal text from a boundary on gives equal pieces.

Defined results: null texts count as empty ones (0 tokens); an edit may empty a text or fill an empty one; spans beyond the end are cut at the end;
edits of an id go to every row of that id, in the order of ``seq`` (then of their other columns), each in terms of the text as the ones before left it;
edits of a null or unknown id do nothing; nulls in an edit count as 0, as 0 and as the empty text.
"""

from __future__ import annotations

import bisect
import itertools
import zlib
from collections.abc import Callable

import numpy as np

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reelspark.llm import byte_bpe
from reelspark.llm.common import Scratch, per_document

LEAF, FAN, AHEAD = 64, 16, 4
Counter = Callable[[list[str]], list[int]]


class Node:
    """Characters, tokens and pieces below; a leaf has lists of piece lengths and counts, an inner node children."""

    __slots__ = ("chars", "tokens", "pieces", "kids", "lengths", "counts")

    def __init__(self, kids: list[Node] | None = None, lengths: list[int] | None = None, counts: list[int] | None = None):
        self.kids, self.lengths, self.counts = kids, lengths, counts
        self.renew()

    def renew(self) -> None:
        if self.kids is not None:
            self.chars, self.tokens, self.pieces = sum([k.chars for k in self.kids]), sum([k.tokens for k in self.kids]), sum([k.pieces for k in self.kids])
        else:
            self.chars, self.tokens, self.pieces = sum(self.lengths), sum(self.counts), len(self.lengths)


def leaves_of(lengths: list[int], counts: list[int]) -> list[Node]:
    return [Node(lengths=lengths[i : i + LEAF], counts=counts[i : i + LEAF]) for i in range(0, len(lengths), LEAF)]


def raised(nodes: list[Node]) -> Node:
    """A root over the nodes."""
    while len(nodes) > 1:
        nodes = [Node(kids=nodes[i : i + FAN]) for i in range(0, len(nodes), FAN)]
    return nodes[0] if nodes else Node(lengths=[], counts=[])


class TokenTree:
    def __init__(self, text: str, split: Callable, count: Counter, leaves: tuple[list[int], list[int]] | None = None):
        """``split(text, at)`` yields pieces from a boundary on, lazily (``at`` None: all at once); ``count`` gives their token counts.
        ``leaves``: the pieces' lengths and counts, if they are known already; then nothing is encoded."""
        self.text, self.split, self.count = text, split, count
        if leaves is None:
            pieces = list(split(text, None))
            leaves = list(map(len, pieces)), count(pieces)
        self.root = raised(leaves_of(*leaves))
        self.encoded = 0  # pieces encoded by edits

    def leaves(self) -> tuple[list[int], list[int]]:
        """Lengths and token counts of all pieces, in order."""
        lengths, counts, todo = [], [], [self.root]
        while todo:
            node = todo.pop()
            if node.kids is None:
                lengths += node.lengths
                counts += node.counts
            else:
                todo += reversed(node.kids)
        return lengths, counts

    @property
    def tokens(self) -> int:
        return self.root.tokens

    def locate(self, at: int) -> tuple[int, int]:
        """(piece index, its start) of the piece that holds character ``at``; the end for at = length."""
        node, start, index = self.root, 0, 0
        while node.kids is not None:
            for kid in node.kids:
                if at < start + kid.chars or kid is node.kids[-1]:
                    node = kid
                    break
                start, index = start + kid.chars, index + kid.pieces
        for length in node.lengths:
            if at < start + length:
                break
            start, index = start + length, index + 1
        return index, start

    def start_of(self, index: int) -> int:
        """Start of the piece with this index."""
        node, start = self.root, 0
        while node.kids is not None:
            for kid in node.kids:
                if index < kid.pieces or kid is node.kids[-1]:
                    node = kid
                    break
                start, index = start + kid.chars, index - kid.pieces
        return start + sum(node.lengths[:index])

    def tokens_before(self, at: int) -> int:
        """Tokens of the whole pieces before character ``at``."""
        node, total, start = self.root, 0, 0
        while node.kids is not None:
            for kid in node.kids:
                if at < start + kid.chars or kid is node.kids[-1]:
                    node = kid
                    break
                start, total = start + kid.chars, total + kid.tokens
        for length, n in zip(node.lengths, node.counts, strict=True):
            if at < start + length:
                break
            start, total = start + length, total + n
        return total

    def edit(self, lo: int, hi: int, new: str) -> int:
        """Replaces text[lo:hi]; returns how many pieces were encoded."""
        old = self.text
        lo, hi = min(lo, len(old)), min(max(lo, hi), len(old))
        safe = lo
        while safe > 0 and old[safe - 1].isspace():
            safe -= 1
        first, begin = self.locate(max(0, safe - AHEAD))
        if first > 0:
            first -= 1
            begin = self.start_of(first)
        self.text = old[:lo] + new + old[hi:]
        shift, edge = len(new) - (hi - lo), lo + len(new)
        pieces, at = [], begin
        last, old_end = self.locate(hi)  # old boundaries from here on may be met again
        bounds = self._starts(last, old_end)
        bound = next(bounds, None)
        for p in self.split(self.text, begin):
            if at >= edge:
                while bound is not None and bound[1] + shift < at:
                    bound = next(bounds, None)
                if bound is not None and bound[1] >= hi and bound[1] + shift == at:
                    break
            pieces.append(p)
            at += len(p)
        else:
            bound = (self.root.pieces, len(old))
        self._replace(first, bound[0], [len(p) for p in pieces], self.count(pieces))
        self.encoded += len(pieces)
        return len(pieces)

    def _starts(self, index: int, start: int):
        """(piece index, start) of the old pieces from one on, then the end."""

        def walk(node: Node, skip: int):
            if node.kids is None:
                yield from node.lengths[skip:]
                return
            for kid in node.kids:
                if skip >= kid.pieces:
                    skip -= kid.pieces
                    continue
                yield from walk(kid, skip)
                skip = 0

        for length in walk(self.root, index):
            yield index, start
            index, start = index + 1, start + length
        yield index, start

    def _replace(self, lo: int, hi: int, lengths: list[int], counts: list[int]) -> None:
        """Pieces lo to hi give way; only nodes on the paths to them are touched."""
        nodes = self._splice(self.root, lo, hi, lengths, counts)
        self.root = raised(nodes)

    def _splice(self, node: Node, lo: int, hi: int, lengths: list[int], counts: list[int]) -> list[Node]:
        if node.kids is None:
            node.lengths[lo:hi], node.counts[lo:hi] = lengths, counts
            if len(node.lengths) > 2 * LEAF:
                return leaves_of(node.lengths, node.counts)
            node.renew()
            return [node] if node.lengths else []
        ends = list(itertools.accumulate(k.pieces for k in node.kids))
        a = min(bisect.bisect_right(ends, lo), len(ends) - 1)
        b = max(a, min(bisect.bisect_left(ends, hi), len(ends) - 1))
        base = ends[a] - node.kids[a].pieces
        out = self._splice(node.kids[a], lo - base, min(hi - base, node.kids[a].pieces), lengths, counts)
        for k in range(a + 1, b + 1):  # what the span takes from later children
            base = ends[k] - node.kids[k].pieces
            out += self._splice(node.kids[k], 0, min(hi - base, node.kids[k].pieces), [], [])
        node.kids[a : b + 1] = out
        if len(node.kids) > 2 * FAN:
            return [Node(kids=node.kids[i : i + FAN]) for i in range(0, len(node.kids), FAN)]
        node.renew()
        return [node] if node.kids else []


def bpe_tools(path: str | None = None, pattern: str | None = None) -> tuple[Callable, Counter]:
    bpe = byte_bpe.shared(path, pattern)

    def split(text: str, at: int | None):
        return itertools.chain.from_iterable(bpe.pieces(text)) if at is None else (m.group() for m in bpe.pattern.finditer(text, at))

    def count(pieces: list[str]) -> list[int]:
        out: list[int] = []
        for at in range(0, len(pieces), 100_000):  # no more than the memory of known pieces can hold
            part = pieces[at : at + 100_000]
            out += map(len, bpe.ids_of(part))
        return out

    return split, count


def pack(leaves: tuple[list[int], list[int]]) -> bytes:
    """Lengths and counts as small numbers (seven bits a byte), compressed."""
    flat = np.array(leaves, np.uint64).reshape(-1)
    if not len(flat):
        return b""
    if flat.max() < 128:
        return zlib.compress(flat.astype(np.uint8).tobytes(), 1)
    digits = max(1, -(-int(flat.max()).bit_length() // 7))
    parts = (flat[:, None] >> np.arange(0, 7 * digits, 7, dtype=np.uint64)) & np.uint64(127)
    last = np.maximum(0, digits - 1 - (parts[:, ::-1] != 0).argmax(axis=1)) * (flat > 0)
    at = np.arange(digits)
    parts |= np.where(at < last[:, None], np.uint64(128), np.uint64(0))
    return zlib.compress(parts.astype(np.uint8)[at <= last[:, None]].tobytes(), 1)


def unpack(data: bytes) -> tuple[list[int], list[int]]:
    if not data:
        return [], []
    raw = np.frombuffer(zlib.decompress(data), np.uint8)
    ends = np.flatnonzero(raw < 128)
    starts = np.r_[0, ends[:-1] + 1]
    values = np.zeros(len(ends), np.uint64)
    for k in range(int((ends - starts).max()) + 1):
        there = starts + k <= ends
        values[there] |= (raw[starts[there] + k] & 127).astype(np.uint64) << np.uint64(7 * k)
    half = len(values) // 2
    return values[:half].tolist(), values[half:].tolist()


STATE = "doc_id bigint, version int, text string, n_tokens bigint, n_pieces bigint, tree binary"


def build(docs: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """The state of every document, version 0: the only time that whole texts are encoded. Write it and read it back."""

    def run(cols: list[list]) -> list[list]:
        split, count = bpe_tools(path, pattern)
        out = []
        for text in cols[1]:
            pieces = list(split(text or "", None))
            counts = count(pieces)
            out.append((0, text or "", sum(counts), len(pieces), pack((list(map(len, pieces)), counts))))
        return [cols[0], *map(list, zip(*out, strict=True))] if out else [[] for _ in range(6)]

    return per_document(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text"), ["doc_id", "text"], STATE, run)


def edited(rows: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """State rows with a column ``edits`` (array of lo, hi, new) -> the new state, with n_tokens_before, n_pieces_before and n_encoded."""

    def run(cols: list[list]) -> list[list]:
        split, count = bpe_tools(path, pattern)
        out = []
        for doc_id, version, text, n_tokens, n_pieces, tree, edits in zip(*cols, strict=True):
            t = TokenTree(text, split, count, unpack(tree))
            for e in edits:
                t.edit(e["lo"] or 0, e["hi"] or 0, e["new"] or "")
            out.append((doc_id, version + 1, t.text, t.tokens, t.root.pieces, pack(t.leaves()), n_tokens, n_pieces, t.encoded))
        return list(map(list, zip(*out, strict=True))) if out else [[] for _ in range(9)]

    names = [c.split()[0] for c in STATE.split(", ")]
    return per_document(rows, [*names, "edits"], STATE + ", n_tokens_before bigint, n_pieces_before bigint, n_encoded bigint", run)


FEW = 100_000  # edited ids up to which they are broadcast


def apply_edits(state: DataFrame, edits: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """The new state after ``edits`` (doc_id, seq, lo, hi, new): versions of edited rows go up by one, other rows stay as they are.

    An id's edits are one list, as they depend on each other; the texts of edited documents are joined with them (broadcast if
    there are at most ``FEW`` ids)."""
    steps = edits.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("bigint").alias("doc_id"), F.struct("seq", F.col("lo").cast("int").alias("lo"), F.col("hi").cast("int").alias("hi"), "new").alias("e"))
    lists = steps.groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_list("e")), lambda e: F.struct(e["lo"].alias("lo"), e["hi"].alias("hi"), e["new"].alias("new"))).alias("edits"))
    lists = Scratch(state, "edits").keep(lists)
    small = lists.count() <= FEW
    aside = F.broadcast if small else lambda x: x
    changed = edited(state.join(aside(lists), "doc_id"), path, pattern)
    same = state.join(aside(lists.select("doc_id")), "doc_id", "left_anti")
    return same.withColumns({"n_tokens_before": F.col("n_tokens"), "n_pieces_before": F.col("n_pieces"), "n_encoded": F.lit(0).cast("bigint")}).unionByName(changed)


def registered_edits() -> Column:
    """The edits of the registered query as a column over ``text``, each in terms of the text as the ones before left it: a heading is
    put in front, the middle eighth goes, and the last word is doubled."""
    n, head = F.length("text"), "Revised copy 1.\n"
    gone = F.floor(n / 8).cast("int")
    mid, end = F.floor(n / 2).cast("int") + len(head), n + len(head) - gone
    # looked for from the end: a pattern tied to the end alone would be tried at every character
    last = F.reverse(F.regexp_extract(F.reverse("text"), r"^[\x20\x09-\x0D]*([^\x20\x09-\x0D]+)", 1))
    one = lambda lo, hi, new: F.struct(lo.cast("int").alias("lo"), hi.cast("int").alias("hi"), new.alias("new"))
    return F.array(one(F.lit(0), F.lit(0), F.lit(head)), one(mid, mid + gone, F.lit("")), one(end, end, F.concat(F.lit(" "), last)))


def digest(docs: DataFrame) -> DataFrame:
    """The columns that op7 returns: a state is built and written, read back, and edited (heading, middle eighth, last word) in every document;
    counts before and after, and the pieces encoded for the edits."""
    state = Scratch(docs, "tokens").keep(build(docs), "zstd")
    out = edited(state.withColumn("edits", registered_edits()))
    return out.select("doc_id", F.col("n_tokens_before").alias("n_tokens"), F.col("n_pieces_before").alias("n_pieces"), F.col("n_tokens").alias("n_tokens_edited"), F.col("n_pieces").alias("n_pieces_edited"), "n_encoded")
