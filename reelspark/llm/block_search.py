"""Exact nearest neighbours by a block matrix join over int8 tiles.

Queries and candidates are dealt to a grid of cells: query group i meets candidate group j in cell
(i, j), an equality join on the cell, with the group counts set by ``QUERIES`` and ``CANDIDATES`` rows
per group. In a cell every vector is quantised to int8; tiles of integer products give each inner product
with a bound on its error (from the vectors' exact quantisation residuals). Pairs whose upper bound
reaches the k-th best lower bound are recomputed in double precision, and a heap per query merges
tiles. Cells return at most k rows a query, merged by one window over those. Nothing is approximate in the result: recall is 1.

Equal vectors in a cell are compared once and stand for their smallest ids (k + 1 of them, as one may
be the query's own), so a vector shared by a third of all rows costs no more than any other.

Products are plain sums in double precision, component by component. Where lengths are so great that a bound or such a sum
could overflow (or so small that it could vanish), every pair goes to the exact path; a sum that is no number (infinite parts of both signs) is
taken over scaled components instead, so that it is infinite only if the product itself is beyond doubles.

Defined results: vectors that are null, empty, zero or hold null or non-finite components take no part, nor
do rows with a null id; a query meets candidates of its own dimension; repeated rows of one id and
vector count once; an id with several vectors is several queries (each with ranks of its own) and several candidates,
but never a neighbour of itself; ties go to the smaller id; fewer than k candidates give fewer rows.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

K, EVERY = 20, 20
QUERIES, CANDIDATES, TILE = 16_384, 16_384, 2_048


def usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return vector.isNotNull() & (F.size(vector) > 0) & fine & F.exists(vector, lambda v: v != 0)


#: Beyond these lengths of a pair's vectors, multiplied, plain sums or bounds might overflow or lose all digits.
GREAT, SMALL = 1e300, 1e-250


def lengths(x: np.ndarray) -> np.ndarray:
    """Norms of rows, free of overflow inside."""
    most = np.abs(x).max(axis=1)
    most = np.where(most > 0, most, 1.0)
    with np.errstate(over="ignore"):
        return np.linalg.norm(x / most[:, None], axis=1) * most


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes, scales, residual norms, norms of the codes' vectors (rows of x, double)."""
    scale = np.abs(x).max(axis=1) / 127
    scale[scale == 0] = np.finfo(float).tiny
    code = np.rint(x / scale[:, None]).clip(-127, 127).astype(np.int8)
    back = code * scale[:, None]
    return code, scale, lengths(x - back), lengths(back)


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Inner products of paired rows, summed in the order of the components."""
    with np.errstate(over="ignore", invalid="ignore"):
        out = a[:, 0] * b[:, 0]
        for d in range(1, a.shape[1]):
            out = out + a[:, d] * b[:, d]
        if (odd := np.isnan(out)).any():
            ea, eb = (np.frexp(np.abs(x[odd]).max(axis=1))[1] for x in (a, b))
            out[odd] = np.ldexp(np.ldexp(products(np.ldexp(a[odd], -ea[:, None]), np.ldexp(b[odd], -eb[:, None])), ea), eb)
    return out


def search_cell(q_ids: np.ndarray, q: np.ndarray, c_ids: np.ndarray, c: np.ndarray, k: int = K) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place of the query, candidate id, score) of the k nearest in one cell, rows of the query's id excluded."""
    order = np.lexsort((c_ids, *c.T[::-1]))
    c_ids, c = c_ids[order], c[order]
    new = np.r_[True, (c[1:] != c[:-1]).any(axis=1)]
    again = np.r_[False, ~new[1:] & (c_ids[1:] == c_ids[:-1])]
    c_ids, c, new = c_ids[~again], c[~again], new[~again]
    starts = np.flatnonzero(new)
    ends = np.r_[starts[1:], len(c_ids)]
    u = c[starts]
    qc, qs, qe, qn = quantise(q)
    uc, us, ue, un = quantise(u)
    length, q_length = lengths(u), lengths(q)
    out_q, out_c, out_s = [], [], []
    for lo in range(0, len(q), TILE):
        part = slice(lo, min(lo + TILE, len(q)))
        heaps: list[list[tuple[float, int]]] = [[] for _ in range(part.stop - lo)]
        floor = np.full(part.stop - lo, -np.inf)
        for at in range(0, len(u), TILE):
            tile = slice(at, min(at + TILE, len(u)))
            # float32 holds the integers below 2**24 exactly; wider vectors use double
            kind = np.float32 if q.shape[1] * 127 * 127 < 1 << 24 else np.float64
            with np.errstate(over="ignore", invalid="ignore"):
                near = (qc[part].astype(kind) @ uc[tile].astype(kind).T).astype(np.float64) * qs[part, None] * us[None, tile]
                bound = qe[part, None] * length[None, tile] + qn[part, None] * ue[None, tile]
                bound = bound * (1 + 1e-9) + 1e-12 * (qn[part, None] + qe[part, None]) * length[None, tile]
                reach = q_length[part, None] * length[None, tile]
                sure = (reach < GREAT) & (reach > SMALL)
                low, high = np.where(sure, near - bound, -np.inf), np.where(sure, near + bound, np.inf)
            if low.shape[1] > k + 1:  # one of the vectors may stand for the query's own row alone
                floor = np.maximum(floor, np.partition(low, low.shape[1] - k - 1, axis=1)[:, low.shape[1] - k - 1])
            i, j = np.nonzero(high >= floor[:, None])
            for s in range(0, len(i), 1 << 17):
                ii, jj = i[s : s + (1 << 17)], j[s : s + (1 << 17)]
                exact = products(q[lo + ii], u[at + jj])
                for a, b, v in zip(ii.tolist(), (at + jj).tolist(), exact.tolist(), strict=True):
                    heap, own = heaps[a], q_ids[lo + a]
                    if len(heap) == k and v < heap[0][0]:
                        continue
                    taken = 0
                    for cid in c_ids[starts[b] : min(ends[b], starts[b] + k + 1)].tolist():
                        if cid == own:
                            continue
                        item = (v, -cid)
                        if len(heap) < k:
                            heapq.heappush(heap, item)
                        elif item > heap[0]:
                            heapq.heapreplace(heap, item)
                        else:
                            break
                        taken += 1
                        if taken == k:
                            break
            full = np.array([h[0][0] if len(h) == k else -np.inf for h in heaps])
            floor = np.maximum(floor, full)
        for a, heap in enumerate(heaps):
            for v, cid in sorted(heap, reverse=True):
                out_q.append(lo + a)
                out_c.append(-cid)
                out_s.append(v)
    return np.array(out_q, np.int64), np.array(out_c, np.int64), np.array(out_s, np.float64)


def nearest(vectors: DataFrame, queries: Column, k: int = K, per_query_group: int = QUERIES, per_candidate_group: int = CANDIDATES, id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest rows by inner product of every row that ``queries`` marks."""
    rows = vectors.where(F.col(id).isNotNull()).select(F.col(id).cast("bigint").alias("id"), F.col(vector).cast("array<double>").alias("v"), F.coalesce(queries, F.lit(False)).alias("is_query"))
    rows = rows.where(usable(F.col("v"))).withColumn("dim", F.size("v"))
    count = rows.agg(F.count("*").alias("n"), F.count_if("is_query").alias("q")).first()
    high, wide = max(1, -(-count["q"] // per_query_group)), max(1, -(-count["n"] // per_candidate_group))
    if wide * high < 24:  # small inputs: still enough cells for the machines
        wide = max(1, min(-(-count["n"] // 512), 24 // high))
    spread = lambda n: F.sequence(F.lit(0), F.lit(n - 1))
    asked = rows.where("is_query").select("id", "v", "dim", F.xxhash64("v").alias("twin"), F.pmod(F.xxhash64("id"), F.lit(high)).cast("int").alias("i"), F.explode(spread(wide)).alias("j"), F.lit(0).alias("side"))
    held = rows.select("id", "v", "dim", F.explode(spread(high)).alias("i"), F.pmod(F.xxhash64("id", F.lit(5)), F.lit(wide)).cast("int").alias("j"), F.lit(1).alias("side"))
    cells = [F.col(c) for c in ("dim", "i", "j")]

    def cell(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"query_id": [], "twin": [], "vec_id": [], "score": []})
        a = a.drop_duplicates(["id", "twin"]) if not a["id"].is_unique else a
        q, c, s = search_cell(a["id"].to_numpy(), np.stack(a["v"].to_numpy()).astype(float), b["id"].to_numpy(), np.stack(b["v"].to_numpy()).astype(float), k)
        return pd.DataFrame({"query_id": a["id"].to_numpy()[q], "twin": a["twin"].to_numpy()[q], "vec_id": c, "score": s})

    found = asked.groupBy(*cells).cogroup(held.groupBy(*cells)).applyInPandas(cell, "query_id bigint, twin bigint, vec_id bigint, score double")
    # cells of one query may share an id's equal vectors, never a (query, candidate row): the window sees at most k rows a cell
    w = Window.partitionBy("query_id", "twin").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def digest(embeddings: DataFrame) -> DataFrame:
    """The columns that op9 returns."""
    return nearest(embeddings, F.col("vec_id") % EVERY == 0)


ORACLE = """
WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE embedding IS NOT NULL AND vec_id IS NOT NULL),
q AS (SELECT a.vec_id AS query_id, b.vec_id, list_reduce(list_transform(range(1, len(a.v) + 1), lambda i: a.v[i] * b.v[i]), lambda x, y: x + y) AS score FROM e a JOIN e b ON a.vec_id <> b.vec_id WHERE a.vec_id % 20 = 0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM q)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""
