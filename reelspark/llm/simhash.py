"""SimHash fingerprints and near-duplicate groups by bit-sliced comparison.

Plan: one pass makes (doc_id, fingerprint) rows; equal fingerprints are merged before anything else
(a third of all rows may be one text). Fingerprints within the radius r agree in at least one of
r + 1 bit blocks (or in ``m - r`` of m blocks), so each fingerprint is dealt to one bucket per block
choice. A bucket is compared in tiles whose bit planes are stored vertically: carry-save counters
update 64 distances at once, and a tile row is abandoned as soon as every distance in
it exceeds the radius. Buckets beyond ``TILE`` rows are cut into chunks and every pair of chunks is a
tile of its own, so no task holds an unbounded bucket. A tile returns a star for each of its groups
(never all pairs), and groups come from min-label contraction over written tables.

Two kinds of fingerprints share all of that. ``near_duplicates``: 64 bits of four-word shingles, radius 4, buckets by block
choices, which lose nothing. ``keep_one`` (pipeline): ``WIDE_BITS`` bits of five-word shingles, radius ``WIDE_RADIUS``, that is a
Jaccard similarity of 0.8 or more; so wide a radius admits no block choices, so that buckets are equal draws of ``key_bits`` bits, as
many tables of them as find a pair at similarity 0.8 with a chance of ``FOUND`` (at 0.9 nearly always, and copies of copies help each other).

Joins whose key may be hot (a fingerprint of a third of all rows, the centre of a giant group) take the hot keys' rows
from a broadcast of at most ``HOT`` rows (keys that hold more than 1 / HOT of all rows) and shuffle the rest.

Defined results: a null or empty text (or one without words) has fingerprint 0 and links like any
other; a null doc_id gets the smallest non-null doc_id of its group, or null if there is none;
repeated rows give repeated results.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reelspark.llm.common import Scratch, fresh, per_document

SHINGLE, RADIUS, SEED = 4, 4, 42
WIDE_SHINGLE, WIDE_BITS, WIDE_RADIUS, FOUND = 5, 256, 46, 0.95
TILE, HOT, SPLIT = 4096, 1000, 20_000


def majority(text: str | None, width: int, digest) -> bytes:
    """Bit by bit, whether over half of the shingles' hashes have it set; ``digest`` gives a hash's bytes, lowest bits first."""
    words = (text or "").encode().lower().split()  # bytes.lower() folds A-Z alone
    if not words:
        return bytes(len(digest(b"")))
    flat, width = b" ".join(words), min(width, len(words))
    ends = list(itertools.accumulate(len(w) + 1 for w in words))
    starts = [0, *ends]
    counts, n = 0, len(words) - width + 1
    for lo in range(0, n, 1 << 15):  # bounded pieces of very long texts
        hi = min(n, lo + (1 << 15))
        values = b"".join([digest(flat[s : e - 1]) for s, e in zip(starts[lo:hi], ends[lo + width - 1 : hi + width - 1], strict=True)])
        counts = counts + np.unpackbits(np.frombuffer(values, np.uint8).reshape(hi - lo, -1), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return np.packbits(2 * counts > n, bitorder="little").tobytes()


def narrow_hash(shingle: bytes) -> bytes:
    return xxhash.xxh64_digest(shingle, SEED)[::-1]


def wide_hash(shingle: bytes) -> bytes:
    return xxhash.xxh3_128_digest(shingle, SEED) + xxhash.xxh3_128_digest(shingle, SEED + 1)


def fingerprint(text: str | None, width: int = SHINGLE) -> int:
    return int.from_bytes(majority(text, width, narrow_hash), "little")


def signed(value: int) -> int:
    return value - (1 << 64) if value >= 1 << 63 else value


def fingerprints(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(doc_id, fp): fp holds the 64 bits as a signed long."""

    def run(cols: list[list]) -> list[list]:
        return [cols[0], [signed(fingerprint(t)) for t in cols[1]]]

    return per_document(docs.select(F.col(key).cast("bigint").alias("doc_id"), F.col(text)), ["doc_id", text], "doc_id bigint, fp bigint", run)


def block_masks(blocks: int, radius: int = RADIUS) -> list[int]:
    """Bit masks of every choice of ``blocks - radius`` of the bit blocks: one of them is equal in any linked pair."""
    edges = [64 * i // blocks for i in range(blocks + 1)]
    one = [((1 << (b - a)) - 1) << a for a, b in itertools.pairwise(edges)]
    return [sum(c) for c in itertools.combinations(one, blocks - radius)]


def choose_blocks(n: int, radius: int = RADIUS) -> int:
    """More blocks mean longer keys but more copies of each row; takes the cheaper for n fingerprints."""
    cost = {}
    for m in range(radius + 1, radius + 4):
        tables, bits = math.comb(m, radius), 64 * (m - radius) // m
        cost[m] = tables * n * (40 + n / 2**bits / 16)
    return min(cost, key=cost.get)


def as_bytes(prints: pd.Series) -> np.ndarray:
    """Fingerprints (longs or binaries) as rows of bytes, lowest bits first."""
    if prints.dtype == object:
        return np.frombuffer(b"".join(map(bytes, prints)), np.uint8).reshape(len(prints), -1)
    return prints.to_numpy().astype("<i8").view(np.uint8).reshape(-1, 8)


def beyond(counters: list[np.ndarray], over: np.ndarray, radius: int) -> np.ndarray:
    """Bit set where a vertical counter exceeds the radius, compared from its highest digit down."""
    more, same = over.copy(), ~over
    for level in range(len(counters) - 1, -1, -1):
        if radius >> level & 1:
            same &= counters[level]
        else:
            more |= same & counters[level]
            same &= ~counters[level]
    return more


def links_in_tile(left: np.ndarray, right: np.ndarray, radius: int = RADIUS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs (i, j) of left x right (rows of bytes) at distance <= radius, by bit planes and carry-save counters; in
    parts, of some rows of left each."""
    words, bits = -(-len(right) // 64), 8 * right.shape[1]
    padded = np.zeros((words * 64, right.shape[1]), np.uint8)
    padded[: len(right)] = right
    # planes[b] holds bit b of every right row, 64 rows to a word
    planes = np.ascontiguousarray(np.packbits(np.unpackbits(padded, axis=1, bitorder="little").T, axis=1, bitorder="little")).view("<u8")
    tail = np.full(words, ~np.uint64(0))
    if len(right) % 64:
        tail[-1] = np.uint64((1 << len(right) % 64) - 1)
    levels, every = max(1, radius.bit_length()), max(8, bits // 16)
    step = max(1, (1 << 15) // words)
    for lo in range(0, len(left), step):
        alive = np.arange(lo, min(lo + step, len(left)))
        flips = np.unpackbits(left[alive], axis=1, bitorder="little").astype("<u8") * ~np.uint64(0)
        counters = [np.zeros((len(alive), words), "<u8") for _ in range(levels)]
        over = np.zeros((len(alive), words), "<u8") | ~tail
        for b in range(0, bits, 2):
            x, y = planes[b] ^ flips[:, b, None], planes[b + 1] ^ flips[:, b + 1, None]
            half = counters[0] ^ x  # two planes and the ones make new ones and a carry of twos
            carry = (counters[0] & x) | (half & y)
            counters[0] = half ^ y
            for level in range(1, levels):
                counters[level], carry = counters[level] ^ carry, counters[level] & carry
            over |= carry
            if b + 2 > 2 * radius and (b + 2) % every == 0 and b + 2 < bits:
                live = (beyond(counters, over, radius) != ~np.uint64(0)).any(axis=1)
                if not live.all():
                    alive, over, flips, counters = alive[live], over[live], flips[live], [c[live] for c in counters]
                    if not len(alive):
                        break
        if len(alive):
            at, word = np.nonzero(~beyond(counters, over, radius))
            near = ~beyond([c[at, word] for c in counters], over[at, word], radius)
            k, bit = np.nonzero(np.unpackbits(near.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
            if len(k):
                yield alive[at[k]], word[k] * 64 + bit


def merged(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Labels (each the smallest index known of its group) after the links (i, j), by hooking and pointer jumping."""
    while True:
        a, b = label[i], label[j]
        apart = a != b
        if not apart.any():
            return label
        i, j, low, high = i[apart], j[apart], np.minimum(a, b)[apart], np.maximum(a, b)[apart]
        np.minimum.at(label, high, low)
        while (up := label[label], (up != label).any())[1]:
            label = up


def compare_group(left: np.ndarray, right: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """A star of links for each group in one tile: left meets right; a tile without a right side meets itself."""
    label, shift = np.arange(len(left) + len(right)), len(left) if len(right) else 0
    for i, j in links_in_tile(left, right if len(right) else left, radius):
        label = merged(label, i, j + shift)
    member = np.flatnonzero(label != np.arange(len(label)))
    return member, label[member]


def tiles(dealt: DataFrame, radius: int, tile: int = TILE) -> DataFrame:
    """Links (a, b) from (fp, t, k): bucket k of table t, cut into chunks where it is large."""
    # chunks of each bucket: 1 for nearly all; counted by a partial aggregate, so a hot bucket is no hot task
    sizes = dealt.groupBy("t", "k").agg(F.ceil(F.count("*") / tile).cast("int").alias("chunks")).where("chunks > 1")
    dealt = dealt.join(sizes, ["t", "k"], "left").withColumn("chunks", F.coalesce("chunks", F.lit(1)))
    own = F.pmod(F.xxhash64("fp", F.lit(7)), F.col("chunks")).cast("int")
    pairs = F.explode(F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda o: F.struct(F.least(o, F.col("own")).alias("i"), F.greatest(o, F.col("own")).alias("j"), (F.col("own") > o).cast("int").alias("side"))))
    dealt = dealt.withColumn("own", own).select("fp", "t", "k", pairs.alias("x")).select("fp", "t", "k", "x.i", "x.j", "x.side")
    kind = dict(dealt.dtypes)["fp"]

    def compare(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("side", kind="stable")
        rows, cut = as_bytes(group["fp"]), int((group["side"] == 0).sum())
        a, b = compare_group(rows[:cut], rows[cut:], radius)
        return pd.DataFrame({"a": group["fp"].to_numpy()[a], "b": group["fp"].to_numpy()[b]})

    return dealt.groupBy("t", "k", "i", "j").applyInPandas(compare, f"a {kind}, b {kind}")


def edges(prints: DataFrame, count: int, blocks: int | None = None, tile: int = TILE) -> DataFrame:
    """Links (a, b) between distinct 64-bit fingerprints ``prints(fp)``, enough to connect every group."""
    masks = block_masks(blocks or choose_blocks(count))
    # few fingerprints: coarser buckets, so that a tile fills its bit planes (more is compared, nothing less)
    coarse = 1 << max(0, min(40, math.ceil(math.log2(max(1, count / 1024)))))
    entry = F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.pmod(F.xxhash64(F.lit(t), F.col("fp").bitwiseAND(signed(m))), F.lit(coarse)).alias("k")) for t, m in enumerate(masks)]))
    return tiles(prints.select("fp", entry.alias("e")).select("fp", "e.t", "e.k"), RADIUS, tile)


def draws(count: int, similarity: float = 0.8) -> np.ndarray:
    """(tables, key bits): the bit places of every table for this many wide fingerprints. Buckets hold 512 to 1,024 of unrelated
    ones (fewer fingerprints are one bucket, which finds all); a bit of a pair at Jaccard similarity s agrees with chance 1 - angle / pi, cos(angle) = 2 s / (1 + s)."""
    bits = max(0, math.ceil(math.log2(max(1, count / 1024))))
    agree = (1 - math.acos(2 * similarity / (1 + similarity)) / math.pi) ** bits
    rng = np.random.default_rng(SEED)
    tables = math.ceil(math.log(1 - FOUND) / math.log(1 - agree)) if bits else 1
    return np.array([rng.choice(WIDE_BITS, bits, replace=False) for _ in range(tables)], np.int64).reshape(tables, bits)


def wide_edges(prints: DataFrame, count: int, tile: int = TILE) -> DataFrame:
    """Links between distinct wide fingerprints ``prints(fp)``."""
    places = draws(count)

    def run(cols: list[list]) -> list[list]:
        bits = np.unpackbits(as_bytes(pd.Series(cols[0], dtype=object)), axis=1, bitorder="little").astype(np.int64)
        keys = (bits[:, places] << np.arange(places.shape[1])).sum(axis=2)
        return [cols[0], keys.tolist()]

    keyed = per_document(prints, ["fp"], "fp binary, keys array<bigint>", run)
    return tiles(keyed.select("fp", F.posexplode("keys").alias("t", "k")), WIDE_RADIUS, tile)


def hot_join(left: DataFrame, right: DataFrame, key: str, weight: str, total: int, split: int = SPLIT) -> DataFrame:
    """left joined with right (one row per key; ``weight``: the key's rows in left, ``total`` in all). Keys with more than a
    ``HOT``-th of all rows are fewer than ``HOT`` and broadcast, so that no task of the shuffle gets more than that share."""
    if total <= split:
        return left.join(right.drop(weight), key)
    hot, cold = F.col(weight) > max(split // HOT, total // HOT), F.col(weight) <= max(split // HOT, total // HOT)
    few = right.where(hot).drop(weight)
    rest = left.join(F.broadcast(few.select(key)), key, "left_anti").join(right.where(cold).drop(weight), key)
    return left.join(F.broadcast(few), key).unionByName(rest)


def components(nodes: DataFrame, links: DataFrame, rounds: int = 60, split: int = SPLIT) -> DataFrame:
    """(node, root, linked) with root the smallest node reachable, by alternating large-star and small-star steps.

    Each step is two aggregations and a join on the far smaller link table; the links of a step are
    written, so that neither lineage nor lost executors cost more than one step, and the step's before removed.
    """
    scratch = Scratch(nodes, "components")
    links = scratch.keep(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    n, state = links.count(), None
    for _ in range(rounds):
        both = links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"), F.count("*").alias("degree"))
        large = hot_join(both, low, "u", "degree", 2 * n, split).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        if n > split:
            large = scratch.keep(large)
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("degree"))
        small = hot_join(large, low, "u", "degree", 2 * n, split).select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        new = scratch.keep(small)
        for old in (links, *([large] if n > split else [])):
            scratch.drop(old)
        links = new
        now = links.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x"), F.sum(F.xxhash64("v", "u").cast("decimal(38,0)")).alias("s")).first()
        if now == state:
            break
        n, state = now["n"], now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return nodes.join(links.select(F.col("u").alias("node"), F.col("v").alias("root")), "node", "left").select("node", F.coalesce("root", "node").alias("root"))


def grouped(prints: DataFrame, find=edges) -> DataFrame:
    """(fp) -> (fp, root): the group of every distinct fingerprint."""
    distinct = Scratch(prints, "prints").keep(prints.select("fp").distinct())
    n = distinct.count()
    return components(distinct.select(F.col("fp").alias("node")), find(distinct, n)).select(F.col("node").alias("fp"), "root")


def near_duplicates(docs: DataFrame, text: str = "text", split: int = SPLIT) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id of the group)."""
    scratch = Scratch(docs, "simhash")
    prints = scratch.keep(fingerprints(docs, text))
    n = prints.count()
    least = prints.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("copies"))
    named = scratch.keep(grouped(prints).join(least, "fp"))
    roots = named.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("members"))
    named = scratch.keep(hot_join(named, roots, "root", "members", n, split).select("fp", "copies", "component_id"))
    return hot_join(prints, named, "fp", "copies", n, split).select("doc_id", hex16(F.col("fp")).alias("fingerprint"), "component_id")


def hex16(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each group stays, whole: the one with the smallest (doc_id, text hash); pipeline stage.

    Groups are of wide fingerprints (five-word shingles, similarity 0.8). Rows that agree in doc_id and text are one document. A
    group of null ids keeps one of its rows.
    """
    a, b, c, row = fresh(docs, "k_text", "k_id", "k_null", "k_row")
    keyed = docs.withColumns({a: F.xxhash64(F.coalesce("text", F.lit(""))), b: F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(1 << 63))), c: F.col("doc_id").isNull()})

    def run(cols: list[list]) -> list[list]:
        return [cols[0], cols[1], cols[2], [majority(t, WIDE_SHINGLE, wide_hash) for t in cols[3]]]

    prints = Scratch(docs, "simhash").keep(per_document(keyed.select(F.col(a).alias("a"), F.col(b).alias("b"), F.col(c).alias("c"), "text"), ["a", "b", "c", "text"], "a bigint, b bigint, c boolean, fp binary", run))
    best = F.min(F.struct("c", "b", "a"))
    firsts = prints.groupBy("fp").agg(best.alias("best"))
    keep = grouped(prints.select("fp"), wide_edges).join(firsts, "fp").groupBy("root").agg(F.min("best").alias("k")).select(F.col("k.a").alias(a), F.col("k.b").alias(b), F.col("k.c").alias(c))
    stay = keyed.join(keep, [a, b, c], "left_semi")
    rest = [x for x, kind in docs.dtypes if x not in ("doc_id", "text") and "map<" not in kind and "variant" not in kind]
    w = Window.partitionBy(a, b, c).orderBy(F.xxhash64(*rest) if rest else F.lit(0))
    return stay.withColumn(row, F.row_number().over(w)).where(F.col(row) == 1).select(*docs.columns)
