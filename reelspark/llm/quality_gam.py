"""Quality classifier: a generalised additive model with pairwise interactions.

Shallow trees are boosted in cycles over one feature (later over one pair) at a time, each on the
feature's bins, so that their sum per feature is a lookup table. A score is then the logistic of an
intercept plus one table entry per feature and pair, found by vectorised binning.

The model is fitted on the driver from at most ``MAX_LABELLED`` labelled rows (by smallest hash of the
id, held-out fold excluded); everything else runs over all rows, row-local, without a shuffle of texts.

Defined results: a null or empty text has all features 0 and a score like any other; with no labelled
row at all every score is 0.5; equal texts score equally; whole texts count.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.llm.common import held_out, per_document, training_labels
from reelspark.llm.quality_rules import _NOT_LETTER, _NOT_UPPER, SYMBOLS, repeat_words

MAX_LABELLED = 20_000
THRESHOLD = 0.3
MODULUS, REMAINDER = 5, 0
FEATURES = ["log_words", "chars_per_word", "symbols", "bangs", "upper", "digits", "punctuation", "distinct_words", "same_as_previous", "most_frequent", "dup_lines", "repeated_windows", "words_per_line", "non_ascii", "pipes_and_breaks"]
_NOT_DIGIT = bytes(b for b in range(256) if not 48 <= b <= 57)
_NOT_ASCII = bytes(range(128))
_PUNCT = b".,;:!?\"'()-"


def features(text: str | None) -> list[float]:
    data = (text or "").encode()
    words = data.split()
    n, size = len(words), len(data)
    if not n:
        return [0.0] * len(FEATURES)
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    letters = len(data.translate(None, _NOT_LETTER))
    lines = [x for x in data.split(b"\n") if x.strip()]
    return [
        float(np.log1p(n)),
        sum(map(len, words)) / n,
        (size - len(data.translate(None, SYMBOLS))) / n,
        data.count(b"!") / n,
        len(data.translate(None, _NOT_UPPER)) / max(1, letters),
        len(data.translate(None, _NOT_DIGIT)) / size,
        (size - len(data.translate(None, _PUNCT))) / n,
        len(counts) / n,
        sum(map(bytes.__eq__, words, words[1:])) / n,
        max(counts.values()) / n,
        1 - len(set(lines)) / max(1, len(lines)),
        repeat_words(words) / n,
        n / max(1, len(lines)),
        len(data.translate(None, _NOT_ASCII)) / size,
        (data.count(b"|") + data.count(b"\n")) / n,
    ]


@dataclass
class Model:
    intercept: float = 0.0
    cuts: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)

    def logit(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.intercept)
        for k, (cuts, table) in enumerate(zip(self.cuts, self.tables, strict=True)):
            out += table[np.searchsorted(cuts, x[:, k], side="left")]
        for a, b, ca, cb, table in self.pairs:
            out += table[np.searchsorted(ca, x[:, a], side="left"), np.searchsorted(cb, x[:, b], side="left")]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logit(x), -30, 30)))


def bin_cuts(values: np.ndarray, bins: int) -> np.ndarray:
    """Midpoints between neighbouring distinct values, thinned to even shares of the rows."""
    distinct = np.unique(values)
    if len(distinct) > bins:
        distinct = np.unique(np.quantile(values, np.linspace(0, 1, bins), method="nearest"))
    return (distinct[:-1] + distinct[1:]) / 2


def _gain(g: np.ndarray, h: np.ndarray, smooth: float) -> np.ndarray:
    return g * g / (h + smooth)


def tree_1d(g: np.ndarray, h: np.ndarray, leaves: int, smooth: float) -> np.ndarray:
    """Step values by bin of a tree with few leaves, from gradient and curvature sums by bin."""
    parts, cg, ch = [(0, len(g))], np.concatenate([[0], np.cumsum(g)]), np.concatenate([[0], np.cumsum(h)])
    while len(parts) < leaves:
        best = (1e-9, None)
        for p, (lo, hi) in enumerate(parts):
            if hi - lo < 2:
                continue
            mid = np.arange(lo + 1, hi)
            gain = _gain(cg[mid] - cg[lo], ch[mid] - ch[lo], smooth) + _gain(cg[hi] - cg[mid], ch[hi] - ch[mid], smooth) - _gain(cg[hi] - cg[lo], ch[hi] - ch[lo], smooth)
            k = int(np.argmax(gain))
            if gain[k] > best[0]:
                best = (gain[k], (p, int(mid[k])))
        if best[1] is None:
            break
        p, cut = best[1]
        parts[p : p + 1] = [(parts[p][0], cut), (cut, parts[p][1])]
    out = np.zeros(len(g))
    for lo, hi in parts:
        out[lo:hi] = (cg[hi] - cg[lo]) / (ch[hi] - ch[lo] + smooth)
    return out


def tree_2d(g: np.ndarray, h: np.ndarray, smooth: float) -> tuple[np.ndarray, float]:
    """One cut on the first axis, then one on the second in each half: step values by cell, and the gain."""
    best, total = (-1.0, None), float(_gain(g.sum(), h.sum(), smooth))
    for cut in range(1, g.shape[0]):
        value, gain = np.zeros_like(g), -total
        for rows in (slice(0, cut), slice(cut, None)):
            gs, hs = g[rows].sum(0), h[rows].sum(0)
            step = tree_1d(gs, hs, 2, smooth)
            value[rows] = step
            for s in np.unique(step):
                gain += float(_gain(gs[step == s].sum(), hs[step == s].sum(), smooth))
        if gain > best[0]:
            best = (gain, value)
    return (best[1], best[0]) if best[1] is not None else (np.zeros_like(g), 0.0)


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 150, rate: float = 0.1, bins: int = 48, grid: int = 8, pairs: int = 6, pair_rounds: int = 40, smooth: float = 4.0) -> Model:
    if not len(y):
        return Model()
    share = np.clip(y.mean(), 0.5 / (len(y) + 1), 1 - 0.5 / (len(y) + 1))
    model = Model(float(np.log(share / (1 - share))))
    model.cuts = [bin_cuts(x[:, k], bins) for k in range(x.shape[1])]
    model.tables = [np.zeros(len(c) + 1) for c in model.cuts]
    at = [np.searchsorted(c, x[:, k], side="left") for k, c in enumerate(model.cuts)]
    logit = np.full(len(y), model.intercept)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-logit))
        return y - p, p * (1 - p)

    for _ in range(rounds):
        for k, table in enumerate(model.tables):
            if len(table) > 1:
                g, h = slopes()
                step = rate * tree_1d(np.bincount(at[k], g, len(table)), np.bincount(at[k], h, len(table)), 3, smooth)
                table += step
                logit += step[at[k]]
    coarse = [bin_cuts(x[:, k], grid) for k in range(x.shape[1])]
    low = [np.searchsorted(c, x[:, k], side="left") for k, c in enumerate(coarse)]

    def cells(a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        shape, (g, h) = (len(coarse[a]) + 1, len(coarse[b]) + 1), slopes()
        flat = low[a] * shape[1] + low[b]
        return np.bincount(flat, g, shape[0] * shape[1]).reshape(shape), np.bincount(flat, h, shape[0] * shape[1]).reshape(shape)

    ranked = sorted(((tree_2d(*cells(a, b), smooth)[1], a, b) for a, b in itertools.combinations(range(x.shape[1]), 2)), reverse=True)
    for gain, a, b in ranked[:pairs]:
        if gain > 1e-6:
            model.pairs.append((a, b, coarse[a], coarse[b], np.zeros((len(coarse[a]) + 1, len(coarse[b]) + 1))))
    for _ in range(pair_rounds):
        for a, b, _, _, table in model.pairs:
            step = rate * tree_2d(*cells(a, b), smooth)[0]
            table += step
            logit += step[low[a], low[b]]
    for k, table in enumerate(model.tables):  # centred, so that a table reads as the feature's own share
        mean = float(table[at[k]].mean())
        table -= mean
        model.intercept += mean
    return model


def feature_rows(docs: DataFrame, *keep: str) -> DataFrame:
    def run(cols: list[list]) -> list[list]:
        return [cols[0], *cols[2:], [features(t) for t in cols[1]]]

    kinds = dict(docs.dtypes)
    return per_document(docs.select("doc_id", "text", *keep), ["doc_id", "text", *keep], "doc_id bigint, " + "".join(f"{k} {kinds[k]}, " for k in keep) + "x array<double>", run)


def taught(docs: DataFrame, labels: DataFrame, bound: int = MAX_LABELLED) -> DataFrame:
    """(doc_id, label, x): the features of at most ``bound`` labelled ids, one row an id however often it occurs (the smallest features)."""
    chosen = training_labels(labels, "quality", MODULUS, REMAINDER, bound)
    joined = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").join(F.broadcast(chosen), "doc_id")
    return feature_rows(joined, "label").groupBy("doc_id").agg(F.min("label").alias("label"), F.min("x").alias("x"))


def train(docs: DataFrame, labels: DataFrame, bound: int = MAX_LABELLED) -> Model:
    """Only (doc_id, label) of at most ``bound`` ids is broadcast; as many feature rows come to the driver."""
    rows = taught(docs, labels, bound).collect()
    rows.sort(key=lambda r: (r["doc_id"], r["x"]))
    return fit(np.array([r["x"] for r in rows], float).reshape(-1, len(FEATURES)), np.array([r["label"] for r in rows], float))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score) of every whole text."""

    def run(cols: list[list]) -> list[list]:
        x = np.array([features(t) for t in cols[1]], float).reshape(-1, len(FEATURES))
        return [cols[0], model.score(x).tolist()]

    return per_document(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text"), ["doc_id", "text"], "doc_id bigint, score double", run)


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The columns that op1 returns."""
    out = score(docs, train(docs, labels))
    return out.select("doc_id", held_out(F.col("doc_id"), MODULUS, REMAINDER).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
