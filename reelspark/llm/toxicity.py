"""Toxicity by maximum-scoring segments.

Tokens of a word (a run of letters, lower-cased) are the whole word, its openings of four and six letters, and every
five letters in a row, so that inflected forms, compounds and words written together are read from end to end. A run of more
than ``LONG`` letters (scripts without spaces) is cut into overlapping words that hold every five letters of it. Each token gets the
log-odds of toxic against other labelled documents under a Dirichlet prior whose shape is the token's frequency over *all*
documents (a document's distinct words count once each); its lower confidence bound counts, and a word weighs what the
heaviest of its tokens weighs, less a drift per word. A linear scan then finds every maximal scoring segment; the best one is
calibrated as an extreme value of its text's length (Gumbel), and a logistic curve over that, the number and the sum of significant
segments gives the score. The logistic is fitted on scores that each labelled document gets from a model of the other folds.

Counting is words in Arrow batches, everything else about tokens DataFrame expressions over the vocabulary. At most
``MAX_LABELLED`` documents (one a labelled id: that of the smallest text hash) teach the model. Positive weights travel to the tasks
in parts of at most ``PART`` tokens: one part as a rule; beyond it the documents pass the parts one after another, each pass
raising the words' weights, so that no token is left out and no task holds more than a part.

Defined results: a null, empty or wordless text has no segment and gets the score of no evidence; with no labelled
rows that is 0; a token that stands in no toxic labelled document weighs nothing; ties and repeated rows score equally.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reelspark.llm.common import Scratch, held_out, per_document, training_labels

MAX_LABELLED = 20_000
MODULUS, REMAINDER, THRESHOLD, FOLDS = 3, 1, 0.7, 3
DRIFT, BOUND_SD, INNER_SD, PRIOR_SHARE = 0.25, 2.33, 6.0, 0.1
OPENINGS, INNER, LONG = (4, 6), 5, 24
PART, FLUSH = 250_000, 500_000
_WORD = re.compile(r"[^\W\d_]+")
#: ASCII other than letters becomes a space; the bytes of other characters stay.
_SPACED = bytes(b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words_of(text: str | None) -> list[str]:
    low = (text or "").lower()
    words = low.encode().translate(_SPACED).decode().split()  # splitting bytes is far cheaper than matching
    if words and not (low.isascii() or "".join(words).isalpha()):
        words = _WORD.findall(low)
    if max(map(len, words), default=0) > LONG:
        step = LONG - INNER + 1
        words = [w[at : at + LONG] for w in words for at in range(0, max(1, len(w) - INNER + 1), step)]
    return words


def tokens_of(word: str) -> set[str]:
    """The word's tokens; the first character tells the kind: whole, opening or inner letters."""
    n = len(word)
    return {"=" + word, *("^" + word[:k] for k in OPENINGS if n > k), *("~" + word[i : i + INNER] for i in range(n - INNER + 1))}


def token_rows(words: DataFrame) -> DataFrame:
    """(word, ...) -> (token, ...): a row for every place of a token in the word; the empty word has the empty token."""
    word, n, first = F.col("word"), F.length("word"), -1 - len(OPENINGS)
    rows = words.withColumn("at", F.explode(F.sequence(F.lit(first), F.greatest(n - INNER, F.lit(-1)))))
    token = F.when(F.col("at") == first, F.when(word == "", word).otherwise(F.concat(F.lit("="), word)))
    for k, size in enumerate(OPENINGS, first + 1):
        token = token.when(F.col("at") == k, F.when(n > size, F.concat(F.lit("^"), F.left(word, F.lit(size)))))
    token = token.otherwise(F.concat(F.lit("~"), F.substring(word, F.col("at") + 1, F.lit(INNER))))
    return rows.withColumn("token", token).where("token IS NOT NULL").drop("word", "at")


@dataclass
class Model:
    """Positive weights in parts of a bounded size, each read from its own rows of ``table`` (token, weight, part)."""

    table: DataFrame | None = None
    parts: int = 0
    rate: float = 1.0  # lambda of the extreme-value law
    log_k: float = 0.0
    curve: tuple[float, ...] = (-30.0, 0.0, 0.0, 0.0)


def segments(hits: list[tuple[int, float]], drift: float = DRIFT) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (first, last, score): hits are (word index, weight), every word costs the drift.

    Candidates keep a link to the last earlier one with a smaller sum before it, so that candidates once passed over
    are never looked at again: linear in the hits.
    """
    first, last, low, high, link = [], [], [], [], []
    total, before = 0.0, -1
    for i, w in hits:
        total -= drift * (i - before - 1)
        left, total, before = total, total + w - drift, i
        if total <= left:
            continue
        begin, k = i, len(low) - 1
        while True:
            while k >= 0 and low[k] >= left:
                k = link[k]
            if k < 0 or high[k] >= total:
                break
            begin, left = first[k], low[k]  # the candidate grows to here and takes in all after it
            back = link[k]
            for column in (first, last, low, high, link):
                del column[k:]
            k = back
        for column, value in zip((first, last, low, high, link), (begin, i, left, total, k), strict=True):
            column.append(value)
    return [(a, b, y - x) for a, b, x, y in zip(first, last, low, high, strict=True)]


class Weigher:
    """Weights of words, by one automaton over the tokens of a part: a whole word stands between blanks, an opening
    behind one and before a letter, inner letters anywhere. Words without a token, nearly all, cost the scan of their letters only."""

    def __init__(self, weights: dict[str, float]):
        import ahocorasick

        self.machine = ahocorasick.Automaton() if weights else None
        found: dict[str, list[tuple[bool, float]]] = {}
        for token, weight in weights.items():
            kind, letters = token[0], token[1:]
            found.setdefault({"=": f" {letters} ", "^": f" {letters}", "~": letters}[kind], []).append((kind == "^", weight))
        for letters, tokens in found.items():
            self.machine.add_word(letters, tokens)
        if self.machine:
            self.machine.make_automaton()

    def __call__(self, words: list[str]) -> list[tuple[int, float]]:
        """(place, weight of the heaviest token) of every word that has one."""
        if not self.machine or not words:
            return []
        flat = " " + " ".join(words) + " "
        best: dict[int, float] = {}
        at, seen = -1, 0
        for end, tokens in self.machine.iter(flat):
            at += flat.count(" ", seen, end)  # blanks passed; the one behind a whole word is not yet
            seen = end
            for opening, weight in tokens:
                if weight > best.get(at, 0.0) and not (opening and flat[end + 1] == " "):
                    best[at] = weight
        return list(best.items())


def damped(words: list[str], hits: list[tuple[int, float]]) -> list[tuple[int, float]]:
    """Weights come from counts of documents: the k-th word of one opening weighs its share by the root of k."""
    seen, out = {}, []
    for i, v in hits:
        key = words[i][: OPENINGS[-1]]
        k = seen[key] = seen.get(key, 0) + 1
        out.append((i, v / math.sqrt(k)))
    return out


def evidence(n_words: int, found: list[tuple[int, int, float]], rate: float, log_k: float) -> tuple[float, float, float]:
    """What the curve takes: best segment as a standard Gumbel excess, log number and sum of the significant ones."""
    if not found:
        return 0.0, 0.0, 0.0
    level = log_k + math.log(n_words + 1)
    strong = [s[2] for s in found if rate * s[2] > level]
    return max(0.0, rate * max(s[2] for s in found) - level), math.log1p(len(strong)), math.log1p(sum(rate * s for s in strong))


def chance(x: tuple[float, float, float], curve: tuple[float, ...]) -> float:
    return 1 / (1 + math.exp(-max(-30.0, min(30.0, curve[0] + sum(c * v for c, v in zip(curve[1:], x, strict=True))))))


def fit_curve(x: np.ndarray, y: np.ndarray, ridge: float = 0.05) -> tuple[float, ...]:
    """Logistic regression with non-negative slopes, by damped Newton steps."""
    if not len(y):
        return (-30.0, 0.0, 0.0, 0.0)
    z = np.column_stack([np.ones(len(y)), x])
    beta = np.zeros(z.shape[1])
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(z @ beta, -30, 30)))
        pull = ridge * np.r_[1e-3, np.ones(x.shape[1])]
        grad, curve = z.T @ (y - p) - pull * beta, (z * (p * (1 - p))[:, None]).T @ z + np.diag(pull + 1e-6)
        step = np.linalg.solve(curve, grad)
        beta = beta + step * min(1.0, 4 / max(1e-9, float(np.abs(step).max())))
        beta[1:] = np.maximum(beta[1:], 0)
    return tuple(float(b) for b in beta)


def extreme_value(scores: np.ndarray, sizes: np.ndarray) -> tuple[float, float]:
    """(lambda, log K) from best segments of documents without the label: moments of a Gumbel law over log length."""
    if len(scores) < 10 or scores.std() < 1e-6:
        return 1.0, 0.0
    rate = float(np.clip(math.pi / math.sqrt(6) / scores.std(), 0.2, 1.0))
    return rate, float(np.mean(rate * scores - np.log(sizes + 1)) - 0.5772)


def places(n: int) -> int:
    """Tokens of a word of n letters, equal ones counted each."""
    return 1 + sum(n > k for k in OPENINGS) + max(0, n - INNER + 1)


def word_counts(docs: DataFrame, cells: int) -> DataFrame:
    """(word, c0, c1, ...): documents of each cell that hold the word; ``docs`` has text and cell. The empty word counts all
    tokens' places, a document's distinct words once each."""
    names = [f"c{k}" for k in range(cells)]
    schema = "word string, " + ", ".join(f"{c} bigint" for c in names)

    def batch_of(counts: list[Counter]) -> pa.RecordBatch:
        for c in counts:
            c[""] = sum([n * places(len(w)) for w, n in c.items()])
        words = list(dict.fromkeys(w for c in counts for w in c))
        return pa.RecordBatch.from_arrays([pa.array(words, pa.string()), *(pa.array([c[w] for w in words], pa.int64()) for c in counts)], names=["word", *names])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = [Counter() for _ in names]
        for batch in it:
            for text, cell in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                counts[cell].update(set(words_of(text)))
            if sum(map(len, counts)) > FLUSH:
                yield batch_of(counts)
                counts = [Counter() for _ in names]
        yield batch_of(counts)

    return docs.select("text", "cell").mapInArrow(run, schema).groupBy("word").agg(*[F.sum(c).alias(c) for c in names])


def token_counts(words: DataFrame) -> DataFrame:
    """(token, c0, ...) from (word, c0, ...), places of equal tokens in a word counted each; the empty token stands for the empty word."""
    return token_rows(words).groupBy("token").agg(*[F.sum(c).alias(c) for c in words.columns if c != "word"])


def weight_column(token: Column, toxic: Column, other: Column, corpus: Column, n_toxic: float, n_other: float, n_corpus: float) -> Column:
    """Lower confidence bound of the log-odds under an informative Dirichlet prior; nothing below 0.

    A word has many inner tokens and takes the heaviest, so theirs is the stricter bound."""
    mass = PRIOR_SHARE * (n_toxic + n_other)
    prior = corpus * F.lit(mass / max(1.0, n_corpus)) + F.lit(1e-3)
    a, b = toxic + prior, other + prior
    odds = F.log(a / F.greatest(F.lit(n_toxic + mass + 1.0) - a, F.lit(0.5))) - F.log(b / F.greatest(F.lit(n_other + mass + 1.0) - b, F.lit(0.5)))
    return F.greatest(F.lit(0.0), odds - F.when(token.startswith("~"), F.lit(INNER_SD)).otherwise(F.lit(BOUND_SD)) * F.sqrt(F.lit(1.0) / a + F.lit(1.0) / b))


def learners(docs: DataFrame, labels: DataFrame, bound: int = MAX_LABELLED) -> DataFrame:
    """(cell, text), cell = 2 * fold + label: one document for each of at most ``bound`` labelled ids, however often an id occurs."""
    chosen = training_labels(labels, "toxic", MODULUS, REMAINDER, bound).withColumn("cell", (F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(FOLDS)) * 2 + F.col("label")).cast("int"))
    joined = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id")
    return joined.groupBy("doc_id", "cell").agg(F.min(F.struct(F.xxhash64("text").alias("h"), "text")).alias("t")).select("cell", "t.text")


def parts_of(table: DataFrame, column: str, parts: int) -> Iterator[dict[str, float]]:
    for k in range(parts):
        yield {r["token"]: r[column] for r in table.where((F.col("part") == k) & (F.col(column) > 0)).select("token", column).collect()}


def hits(docs: DataFrame, keep: list[str], table: DataFrame, parts: int, columns: list[str], scratch: Scratch) -> DataFrame:
    """``keep``, text, and for every weight column of the table the text's weighted words (hits_0, hits_1, ...).

    One part is one pass; with more, the passes follow each other over a written table.
    """
    kinds = dict(docs.dtypes)
    made = [f"hits_{k}" for k in range(len(columns))]
    empty = F.array().cast("array<struct<at:bigint,weight:double>>")
    rows = docs.select(*keep, F.coalesce("text", F.lit("")).alias("text"), *([empty.alias(m) for m in made] if parts != 1 else []))
    schema = ", ".join(f"{c} {kinds[c]}" for c in keep) + ", text string, " + ", ".join(f"{m} array<struct<at:bigint,weight:double>>" for m in made)
    width = len(keep) + 1
    for k, weights in enumerate(zip(*[parts_of(table, c, parts) for c in columns], strict=True) if parts else []):

        def run(cols: list[list], weights=weights, ready=[]) -> list[list]:  # noqa: B006
            if not ready:
                ready.extend(map(Weigher, weights))
            out = [[] for _ in made]
            old = cols[width:] or [[()] * len(cols[0])] * len(made)
            for row, text in enumerate(cols[width - 1]):
                words = words_of(text)
                for into, weigher, before in zip(out, ready, old, strict=True):
                    best = {h["at"]: h["weight"] for h in before[row]}
                    for i, v in weigher(words):
                        best[i] = max(v, best.get(i, 0.0))
                    into.append([{"at": i, "weight": best[i]} for i in sorted(best)])
            return [*cols[:width], *out]

        rows = per_document(rows, rows.columns, schema, run)
        if k + 1 < parts:
            rows = scratch.keep(rows)
    return rows


def fold_weights(docs: DataFrame, learned: DataFrame, scratch: Scratch, part: int = PART) -> tuple[DataFrame, int]:
    """The table (token, part, w, w0, w1, ...) of all positive weights, whole and without each fold, and its number of parts."""
    cells = 2 * FOLDS
    all_cells = [f"c{k}" for k in range(cells)]
    taught = scratch.keep(token_counts(word_counts(learned, cells)).withColumn("toxic", sum((F.col(c) for c in all_cells[1::2]), F.lit(0))))
    sums = taught.where("token = ''").first()
    asked = taught.where("toxic > 0 AND token <> ''")
    wanted = asked.select("token").unionByName(taught.where("token = ''").select("token"))
    # summed before they meet the tokens asked for: sums are far fewer than places
    corpus = scratch.keep(token_counts(word_counts(docs.select("text", F.lit(0).alias("cell")), 1)).join(wanted, "token", "left_semi").select("token", F.col("c0").alias("corpus")))
    n_corpus = float(corpus.where("token = ''").first()["corpus"])
    rows = asked.join(corpus, "token", "left").withColumn("corpus", F.coalesce("corpus", F.lit(0)).cast("double"))
    made = {}
    for name, but in [("w", None), *((f"w{f}", f) for f in range(FOLDS))]:
        tox = [f"c{2 * f + 1}" for f in range(FOLDS) if f != but]
        oth = [f"c{2 * f}" for f in range(FOLDS) if f != but]
        total = lambda cols: sum((F.col(c) for c in cols), F.lit(0)).cast("double")
        made[name] = weight_column(F.col("token"), total(tox), total(oth), F.col("corpus"), float(sum(sums[c] for c in tox)), float(sum(sums[c] for c in oth)), n_corpus)
    rows = rows.withColumns(made).where(F.greatest(*made) > 0).select("token", *made)
    table = scratch.keep(rows)
    parts = -(-table.count() // part)
    return table.withColumn("part", F.pmod(F.xxhash64("token"), F.lit(max(1, parts))).cast("int")), parts


def train(docs: DataFrame, labels: DataFrame, bound: int = MAX_LABELLED, part: int = PART) -> Model:
    scratch = Scratch(docs, "toxicity")
    learned = scratch.keep(learners(docs, labels, bound))
    if learned.isEmpty():
        return Model()
    table, parts = fold_weights(docs, learned, scratch, part)
    schema = "cell int, n bigint, s array<double>"
    if parts <= 1:  # one pass, each document with the weights of the other folds
        folds, ready = [next(parts_of(table, f"w{f}", 1)) if parts else {} for f in range(FOLDS)], []

        def whole(cols: list[list]) -> list[list]:
            if not ready:
                ready.extend(map(Weigher, folds))
            texts = list(map(words_of, cols[1]))
            return [cols[0], list(map(len, texts)), [[s[2] for s in segments(damped(w, ready[c // 2](w)))] for c, w in zip(cols[0], texts, strict=True)]]

        rows = per_document(learned, ["cell", "text"], schema, whole).collect()
    else:
        found = hits(learned, ["cell"], table, parts, [f"w{f}" for f in range(FOLDS)], scratch)

        def last(cols: list[list]) -> list[list]:
            texts = list(map(words_of, cols[1]))
            mine = [[(h["at"], h["weight"]) for h in cols[2 + c // 2][row]] for row, c in enumerate(cols[0])]
            return [cols[0], list(map(len, texts)), [[s[2] for s in segments(damped(w, m))] for w, m in zip(texts, mine, strict=True)]]

        rows = per_document(found, found.columns, schema, last).collect()
    y = np.array([r["cell"] % 2 for r in rows], float)
    best, sizes = np.array([max(r["s"], default=0.0) for r in rows]), np.array([r["n"] for r in rows], float)
    order = np.lexsort([best, sizes, y])  # rows come in any order
    y, best, sizes, rows = y[order], best[order], sizes[order], [rows[k] for k in order]
    rate, log_k = extreme_value(best[y == 0], sizes[y == 0])
    x = np.array([evidence(r["n"], [(0, 0, s) for s in r["s"]], rate, log_k) for r in rows], float).reshape(-1, 3)
    order = np.lexsort([*x.T, y])
    return Model(table, parts, rate, log_k, fit_curve(x[order], y[order]))


def over_segments(docs: DataFrame, model: Model, column: str, finish: Callable) -> DataFrame:
    """doc_id and ``finish(number of words, maximal segments)`` of every text, as the named column."""
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    schema = f"doc_id bigint, {column}"
    if model.parts <= 1:  # one pass
        weights, ready = next(parts_of(model.table, "w", 1)) if model.parts else {}, []

        def whole(cols: list[list]) -> list[list]:
            if not ready:
                ready.append(Weigher(weights))
            texts = map(words_of, cols[1])
            return [cols[0], [finish(len(w), segments(damped(w, ready[0](w)))) for w in texts]]

        return per_document(rows, ["doc_id", "text"], schema, whole)
    weighed = hits(rows, ["doc_id"], model.table, model.parts, ["w"], Scratch(docs, "toxicity"))

    def last(cols: list[list]) -> list[list]:
        return [cols[0], [finish(len(w), segments(damped(w, [(h["at"], h["weight"]) for h in hs]))) for w, hs in zip(map(words_of, cols[1]), cols[2], strict=True)]]

    return per_document(weighed, ["doc_id", "text", "hits_0"], schema, last)


def passages(docs: DataFrame, model: Model) -> DataFrame:
    """Every maximal segment of every text: first and last word, score, p-value of so high a segment by chance."""
    rate, log_k = model.rate, model.log_k

    def finish(n: int, found: list[tuple[int, int, float]]) -> list[dict]:
        return [{"first": a, "last": b, "score": s, "p": -math.expm1(-math.exp(min(30.0, log_k + math.log(n + 1) - rate * s)))} for a, b, s in found]

    return over_segments(docs, model, "segments array<struct<first:bigint,last:bigint,score:double,p:double>>", finish)


def score(docs: DataFrame, model: Model) -> DataFrame:
    rate, log_k, curve = model.rate, model.log_k, model.curve
    return over_segments(docs, model, "score double", lambda n, found: chance(evidence(n, found, rate, log_k), curve))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The columns that op10 returns."""
    out = score(docs, train(docs, labels))
    return out.select("doc_id", held_out(F.col("doc_id"), MODULUS, REMAINDER).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
