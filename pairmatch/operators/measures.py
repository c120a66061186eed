"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def _pct(num: Column, den: Column) -> Column:
    return F.round(F.coalesce(F.try_divide(num.cast("double"), den), F.lit(0.0)) * 100, 4)


def confusion(df: DataFrame, by: tuple[str, ...] = (), y: str = "y", pred: str = "pred") -> DataFrame:
    one = lambda a, b: F.count_if((F.col(y) == a) & (F.col(pred) == b))
    return df.groupBy(*by).agg(one(1, 1).alias("tp"), one(0, 1).alias("fp"), one(0, 0).alias("tn"), one(1, 0).alias("fn"))


def prf(df: DataFrame, by: tuple[str, ...] = (), y: str = "y", pred: str = "pred") -> DataFrame:
    """tp, fp, fn and precision, recall, f1 of the yes class in per cent; 0 where undefined."""
    c = confusion(df, by, y, pred)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return c.select(*by, "tp", "fp", "fn", _pct(tp, tp + fp).alias("precision"), _pct(tp, tp + fn).alias("recall"), _pct(2 * tp, 2 * tp + fp + fn).alias("f1"))


def tpr_tnr(selected: DataFrame, by: tuple[str, ...] = (), y: str = "y", pseudo: str = "pseudo") -> DataFrame:
    """Quality of pseudo-labels against hidden truth, over selected rows alone; null where a class is missing."""
    c = confusion(selected, by, y, pseudo)
    rate = lambda a, b: F.round(F.try_divide(F.col(a).cast("double"), F.col(a) + F.col(b)), 6)
    return c.select(*by, (F.col("tp") + F.col("fp") + F.col("tn") + F.col("fn")).alias("selected"), rate("tp", "fn").alias("tpr"), rate("tn", "fp").alias("tnr"))


def pr_curve(df: DataFrame, score: str = "p_yes", y: str = "y") -> DataFrame:
    """Cumulative true and all positives by descending score; ties share a row."""
    from pyspark.sql import Window

    at = df.groupBy(score).agg(F.sum(y).alias("pos"), F.count("*").alias("n"))  # scores are rounded: bounded by their digits
    w = Window.orderBy(F.desc(score)).rowsBetween(Window.unboundedPreceding, 0)
    return at.select(score, F.sum("pos").over(w).alias("tp"), F.sum("n").over(w).alias("predicted"))


def example_epochs(n: int, e_r: float, epochs: int = 30, every: int = 8) -> int:
    """Training rows processed over all epochs when a share leaves every so often."""
    total = 0
    for epoch in range(1, epochs + 1):
        total += n
        if epoch % every == 0 and epoch < epochs:
            n -= int(n * e_r + 1e-9)
    return total


def time_cut(seconds_pruned: float, seconds_full: float) -> float:
    return 1 - seconds_pruned / seconds_full


def peak_memory_mb() -> float:
    import resource

    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


def numeric_share(records: DataFrame, values: str) -> DataFrame:
    """Share of attribute values that are numbers; values: array<string> column."""
    v = records.select(F.explode(values).alias("v")).where(F.col("v").isNotNull() & (F.col("v") != ""))
    return v.agg(F.count("*").alias("n"), F.count_if(F.col("v").rlike(r"^-?[0-9]+([.][0-9]+)?$")).alias("numeric")).select("n", "numeric", F.round(F.col("numeric") / F.col("n"), 6).alias("share"))
