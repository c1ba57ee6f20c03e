"""Running sums over keys of any size: a window never holds more than a block.

Rows are cut into blocks of the order column's values; a row's sum is that of the blocks before (a window over one row a
block) and of the rows before it inside its own block.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BLOCK = 4096


def running(rows: DataFrame, by: list[str], order: str, value: str, name: str, block: int = BLOCK, then: list[str] | None = None, whole: dict[str, str] | None = None) -> DataFrame:
    """``rows`` with ``name``: the sum of ``value`` over the rows before, of the same ``by`` (nulls are a key like any other), in the order of
    ``order`` (a whole number, nulls first) and ``then``. ``whole`` may name columns for the key's 'sum' and its 'last' order value."""
    cut, firsts = "_cut", Window.partitionBy(*by).orderBy("_at").rowsBetween(Window.unboundedPreceding, -1)
    b = rows.withColumn(cut, F.coalesce(F.floor(F.col(order) / F.lit(block)).cast("bigint"), F.lit(-(1 << 62))))
    inner = F.sum(value).over(Window.partitionBy(*by, cut).orderBy(order, *(then or [])).rowsBetween(Window.unboundedPreceding, -1))
    sums = b.groupBy(*by, F.col(cut).alias("_at")).agg(F.sum(value).alias("_sum"), F.max(order).alias("_last"))
    over_all = Window.partitionBy(*by).orderBy("_at").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    extra = [{"sum": F.sum("_sum"), "last": F.max("_last")}[k].over(over_all).alias(n) for k, n in (whole or {}).items()]
    starts = sums.select(*[F.col(c).alias(f"_by_{c}") for c in by], "_at", F.coalesce(F.sum("_sum").over(firsts), F.lit(0)).alias("_base"), *extra)
    on = F.col(cut) == F.col("_at")
    for c in by:
        on = on & F.col(c).eqNullSafe(F.col(f"_by_{c}"))
    joined = b.withColumn("_inner", F.coalesce(inner, F.lit(0))).join(starts, on)
    return joined.withColumn(name, F.col("_base") + F.col("_inner")).drop(cut, "_at", "_base", "_inner", *[f"_by_{c}" for c in by])


def numbered(rows: DataFrame, by: list[str], order: str, name: str, block: int = BLOCK, then: list[str] | None = None) -> DataFrame:
    """``rows`` with ``name``: how many rows of the same ``by`` come before."""
    return running(rows.withColumn("_one", F.lit(1).cast("bigint")), by, order, "_one", name, block, then).drop("_one")
