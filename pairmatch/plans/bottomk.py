"""The k lowest rows of any number, exactly, without one task that holds them.

An ordered limit merges k rows in one task, which is right while k is small. Beyond
that, histograms of a total integer order (score, tie hash, id hash) are taken level by
level, each with at most BINS bins, until the bin that holds the k-th row is cut
exactly; selection and rest are then plain filters on the scored table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.plans.dialect import spark_sql

BINS = 1 << 16
SMALL = 100_000


def tie(id_col: str) -> Column:
    return F.expr(spark_sql(f"H('tie|' || {id_col})"))


def boundary(df: DataFrame, score: str, id_col: str, k: int) -> Column | None:
    """Predicate for the k rows lowest by (score, tie hash, id); None if k takes no row.

    score: a bigint column without nulls. df is read a few times: pass a stored table.
    """
    if k <= 0:
        return None
    keys = df.select(F.col(score).cast("long").alias("a"), tie(id_col).alias("b"), F.col(id_col).alias("c"))
    if k <= SMALL:
        last = keys.orderBy("a", "b", "c").limit(k).agg(F.max(F.struct("a", "b", "c")).alias("m")).first()["m"]
        if last is None:
            return None
        a, b, c = last["a"], last["b"], last["c"]
    else:
        left = k
        a, left = _kth(keys.select("a"), "a", left)
        same = keys.where(F.col("a") == a)
        b, left = _kth(same.select("b"), "b", left)
        same = same.where(F.col("b") == b)
        c = same.orderBy("c").limit(left).agg(F.max("c")).first()[0]  # rows of one score and one 32-bit hash
    s, t, i = F.col(score).cast("long"), tie(id_col), F.col(id_col)
    return (s < a) | ((s == a) & ((t < b) | ((t == b) & (i <= c))))


def _kth(df: DataFrame, col: str, k: int) -> tuple[int, int]:
    """Value of the k-th lowest row (the highest, if fewer), and k within that value."""
    low, high, n = df.agg(F.min(col), F.max(col), F.count("*")).first()
    k = min(k, n)
    while low < high:
        width = (high - low) // BINS + 1
        bin_ = F.floor((F.col(col) - low) / width).cast("long").alias("bin")
        counts = sorted(df.where(F.col(col).between(low, high)).groupBy(bin_).count().collect())  # at most BINS rows
        for at, rows in counts:
            if k <= rows:
                low, high = low + at * width, min(high, low + at * width + width - 1)
                break
            k -= rows
    return low, k


def split_bottom(df: DataFrame, score: str, id_col: str, k: int) -> tuple[DataFrame, DataFrame]:
    """(the k lowest, the rest)."""
    lowest = boundary(df, score, id_col, k)
    if lowest is None:
        return df.limit(0), df
    return df.where(lowest), df.where(~lowest)
