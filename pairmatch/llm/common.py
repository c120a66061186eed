"""Helpers that several operators of this subpackage share."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.plans.session import checkpoint_root, cut

__all__ = ["checkpoint_root", "cut", "stored", "stored_lean", "lean", "give_back", "crc_mod", "table", "ascii_lower", "fit_logistic", "sigmoid"]

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stored(df: DataFrame, name: str) -> DataFrame:
    """Written to the shared folder as Parquet and read again: cut lineage, small files."""
    path = f"{checkpoint_root(df.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def give_back():
    """Freed memory to the system: workers are kept between stages, with what their allocators hold."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim is not None:
        trim(0)


ARROW_ROWS, ARROW_CONF = 1_000, "spark.sql.execution.arrow.maxRecordsPerBatch"


def stored_lean(df: DataFrame, name: str) -> DataFrame:
    """stored, with so many rows at once between the JVM and Python workers: texts and sets of them are long."""
    conf = df.sparkSession.conf
    was = conf.get(ARROW_CONF)
    conf.set(ARROW_CONF, str(ARROW_ROWS))
    try:
        return stored(df, name)
    finally:
        conf.set(ARROW_CONF, was)


def lean(run):
    """A function of batches that hands their results on as they come, and freed memory back to the system at the end of its task."""

    def leaner(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return leaner


def crc_mod(doc_id: Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; null ids count as remainder -1."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % n, F.lit(-1))


def ascii_lower(text: Column) -> Column:
    """Lower case for A-Z alone."""
    return F.translate(text, UPPER, LOWER)


def sigmoid(z):
    import numpy as np

    return 1.0 / (1.0 + np.exp(-np.clip(z, -40, 40)))


def fit_logistic(x, y, ridge: float = 1e-3, steps: int = 60):
    """Class-balanced logistic regression by Newton steps.

    x: (n, d) features; returns (weights (d,), bias). With one class only, or no
    rows, the weights are 0 and the bias leans to that class.
    """
    import numpy as np

    x = np.asarray(x, float).reshape(len(y), -1)
    y = np.asarray(y, float)
    pos, neg = y.sum(), (1 - y).sum()
    if pos == 0 or neg == 0:
        return np.zeros(x.shape[1]), (0.0 if len(y) == 0 else (2.0 if pos else -2.0))
    mean, std = x.mean(0), x.std(0) + 1e-12
    a = np.c_[(x - mean) / std, np.ones(len(x))]
    row_w = np.where(y > 0, 0.5 / pos, 0.5 / neg)
    w = np.zeros(a.shape[1])
    for _ in range(steps):
        p = sigmoid(a @ w)
        pen = np.r_[np.full(a.shape[1] - 1, ridge), 1e-9]
        grad = a.T @ (row_w * (p - y)) + pen * w
        hess = (a * (row_w * p * (1 - p))[:, None]).T @ a + np.diag(pen + 1e-12)
        step = np.linalg.solve(hess, grad)
        norm = math.sqrt(float(step @ step))
        w -= step * min(1.0, 4.0 / max(norm, 1e-9))
        if norm < 1e-9:
            break
    return w[:-1] / std, float(w[-1] - (w[:-1] * mean / std).sum())
