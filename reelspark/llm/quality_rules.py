"""Quality rules kept as a ledger: every rule is evaluated once and leaves a bit and its measurement.

Policies are named sets of bits, so a changed policy or an ablation ("what would be kept without
rule r?") is bit arithmetic over the ledger and never reads a text again.

Defined results: a null or empty text has no words, which fails the length rule; equal rows give
equal rows; long texts are handled whole (beyond ``WIDE`` words by array operations instead of sets).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reelspark.llm.common import fresh, per_document

SYMBOLS = b"#*$%&|<>"
MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_bangs", "n_upper", "n_letters"]
LEDGER = "doc_id bigint, " + ", ".join(f"{m} bigint" for m in MEASURES)
WIDE = 200_000
_LETTERS = bytes(range(65, 91)) + bytes(range(97, 123))
_NOT_UPPER = bytes(b for b in range(256) if not 65 <= b <= 90)
_NOT_LETTER = bytes(b for b in range(256) if b not in _LETTERS)


def _rules(at: dict[str, str] | None = None) -> dict[str, Column]:
    """Rule name -> failed, over the measurements; integers only, so that SQL agrees to the bit. ``at``: their columns' names, where others."""
    c = lambda m: F.col((at or {}).get(m, m))
    return {
        "too_short": c("n_words") < 50,
        "repeated_windows": 100 * c("n_repeat_words") > 50 * c("n_words"),
        "symbols": 100 * c("n_symbols") > 25 * c("n_words"),
        "duplicate_lines": 100 * c("n_dup_lines") > 50 * c("n_lines"),
        "shouting": 100 * c("n_bangs") > 30 * c("n_words"),
        "upper_case": 100 * c("n_upper") > 60 * c("n_letters"),
        "long_words": c("word_chars") > 40 * c("n_words"),
    }


RULES = ["too_short", "repeated_windows", "symbols", "duplicate_lines", "shouting", "upper_case", "long_words"]
#: Versioned policies: a document is rejected if any of the named rules failed.
POLICIES = {"base": RULES[:2], "v1": RULES}


def mask(rules: list[str]) -> int:
    return sum(1 << RULES.index(r) for r in rules)


def repeat_words(words: list[bytes]) -> int:
    """Words that lie in a window of three words which occurs at least twice."""
    n = len(words)
    if n < 4:
        return 0
    if n > WIDE:
        ids: dict[bytes, int] = {}
        v = np.fromiter((ids.setdefault(w, len(ids)) for w in words), np.int64, n)
        two = np.unique(v[:-1] * len(ids) + v[1:], return_inverse=True)[1]
        _, three, count = np.unique(two[:-1] * len(ids) + v[2:], return_inverse=True, return_counts=True)
        at = np.flatnonzero(count[three] > 1)
    else:
        windows = list(zip(words, words[1:], words[2:], strict=False))
        seen = set(windows)
        if len(seen) == len(windows):
            return 0
        once, twice = set(), set()
        for w in windows:
            if w in once:
                twice.add(w)
            else:
                once.add(w)
        at = np.array([i for i, w in enumerate(windows) if w in twice])
    hit = np.zeros(n, bool)
    for k in range(3):
        hit[at + k] = True
    return int(hit.sum())


def measure(text: str | None) -> tuple[int, ...]:
    data = (text or "").encode()
    words = data.split()
    white = sum(map(data.count, (b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r")))
    lines = [x for x in data.split(b"\n") if x.strip(b" \t\x0b\x0c\r")]
    return (
        len(words), len(text or "") - white, len(data) - len(data.translate(None, SYMBOLS)), len(lines) - len(set(lines)), repeat_words(words),
        len(lines), data.count(b"!"), len(data.translate(None, _NOT_UPPER)), len(data.translate(None, _NOT_LETTER)),
    )


def measurements(docs: DataFrame, text: str = "text") -> DataFrame:
    def run(cols: list[list]) -> list[list]:
        rows = [measure(t) for t in cols[1]]
        return [cols[0], *map(list, zip(*rows, strict=True))] if rows else [[] for _ in range(len(MEASURES) + 1)]

    return per_document(docs.select(F.col("doc_id").cast("bigint"), F.col(text)), ["doc_id", text], LEDGER, run)


def failed_bits(at: dict[str, str] | None = None) -> Column:
    """Bit i is set if rule i failed."""
    rules = _rules(at)
    return sum((F.when(rules[r], F.lit(1 << i)).otherwise(F.lit(0)) for i, r in enumerate(RULES)), F.lit(0)).cast("bigint")


def ledger(docs: DataFrame) -> DataFrame:
    """doc_id, every measurement, and ``failed``: bit i is set if rule i failed."""
    return measurements(docs).withColumn("failed", failed_bits())


def with_ledger(docs: DataFrame) -> tuple[DataFrame, str]:
    """The documents, all columns and rows, with their ledger beside them, and the name of the failure bits' column.

    Measured on each row itself: no join back, so nulls and repeats in doc_id do no harm.
    """
    from collections.abc import Iterator

    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import LongType, StructField, StructType

    *names, failed = fresh(docs, *MEASURES, "failed")
    schema = StructType([*docs.schema.fields, *(StructField(n, LongType()) for n in names)])
    arrow, at = to_arrow_schema(schema), docs.columns.index("text")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            rows = [measure(t) for t in batch.column(at).to_pylist()]
            made = [pa.array([r[k] for r in rows], pa.int64()) for k in range(len(names))]
            yield pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip([*batch.columns, *made], arrow, strict=True)], schema=arrow)

    return docs.mapInArrow(run, schema).withColumn(failed, failed_bits(dict(zip(MEASURES, names, strict=True)))), failed


def verdict(policy: str = "v1", failed: str = "failed") -> Column:
    return F.col(failed).bitwiseAND(mask(POLICIES[policy])) == 0


def ablation(book: DataFrame, policy: str = "v1") -> DataFrame:
    """Per rule of the policy: documents it fails, and those that would be kept if it alone were dropped."""
    p = mask(POLICIES[policy])
    kept = [F.struct(F.lit(r).alias("rule"), F.count_if(F.col("failed").bitwiseAND(1 << RULES.index(r)) != 0).alias("n_failed"), F.count_if(F.col("failed").bitwiseAND(p & ~(1 << RULES.index(r))) == 0).alias("kept_without"), F.count_if(F.col("failed").bitwiseAND(p) == 0).alias("kept")) for r in POLICIES[policy]]
    return book.agg(F.array(*kept).alias("a")).select(F.inline("a"))


def summary(book: DataFrame) -> DataFrame:
    """Bitwise aggregation of the whole ledger: rules that any, and that every, document fails."""
    return book.agg(F.count("*").alias("n"), F.bit_or("failed").alias("any_failed"), F.bit_and("failed").alias("all_failed"), F.count_if(F.col("failed") == 0).alias("clean"))


def apply_rules(docs: DataFrame, policy: str = "v1") -> DataFrame:
    """The documents that the policy keeps, with all their columns and rows (pipeline stage): the ledger's bits decide."""
    book, failed = with_ledger(docs)
    return book.where(verdict(policy, failed)).select(*docs.columns)


def digest(docs: DataFrame) -> DataFrame:
    """The columns that op8 returns."""
    return ledger(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", (~verdict("base")).alias("base_failed"), verdict("v1").alias("kept"), "failed")


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT rid, doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM d),
t AS (SELECT rid, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] AS g FROM (SELECT rid, words, unnest(range(1, len(words) - 1)) AS i FROM w)),
r AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS n FROM t) WHERE n > 1),
p AS (SELECT rid, count(DISTINCT i + k) AS n FROM r, (SELECT unnest([0, 1, 2]) AS k) GROUP BY rid),
m AS (SELECT doc_id, len(words) AS n_words, list_sum(list_transform(words, lambda x: length(x))) AS wc, length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols,
  len(lines) AS n_lines, len(lines) - len(list_distinct(lines)) AS n_dup_lines, coalesce(p.n, 0) AS n_repeat_words, length(text) - length(replace(text, '!', '')) AS n_bangs,
  length(text) - length(regexp_replace(text, '[A-Z]', '', 'g')) AS n_upper, length(text) - length(regexp_replace(text, '[A-Za-z]', '', 'g')) AS n_letters FROM w LEFT JOIN p USING (rid)),
f AS (SELECT *, coalesce(wc, 0) AS word_chars, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m),
b AS (SELECT *, (CASE WHEN n_words < 50 THEN 1 ELSE 0 END) + (CASE WHEN 100 * n_repeat_words > 50 * n_words THEN 2 ELSE 0 END) + (CASE WHEN 100 * n_symbols > 25 * n_words THEN 4 ELSE 0 END)
  + (CASE WHEN 100 * n_dup_lines > 50 * n_lines THEN 8 ELSE 0 END) + (CASE WHEN 100 * n_bangs > 30 * n_words THEN 16 ELSE 0 END) + (CASE WHEN 100 * n_upper > 60 * n_letters THEN 32 ELSE 0 END) + (CASE WHEN word_chars > 40 * n_words THEN 64 ELSE 0 END) AS failed FROM f)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words,
  base_failed, failed = 0 AS kept, CAST(failed AS BIGINT) AS failed FROM b
"""
