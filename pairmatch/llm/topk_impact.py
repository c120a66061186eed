"""Exact top-k inner products by an impact-ordered, score-at-a-time index.

Vectors become integers and are dealt into blocks of a bounded size. Each block
holds posting segments: for one dimension and one quantised signed impact, the
rows of the block that have it. A query takes segments by descending bound on
their share of its score, adds the segment's quantised impact to the accumulators
of its rows, and stops once proof is at hand: what is still unseen, plus all
rounding, can no longer lift a row outside the candidate set above the k-th best.
Candidates are rescored exactly on the stored integers.

Queries meet blocks, not rows: each query block is sent once to each vector block.

Defined results: null vectors, and vectors with a null, NaN or infinite component,
or a null id, take no part; vectors of unequal length compare as if padded with
zeros; repeated query ids count once (smallest vector); repeated candidate rows are
all candidates; ties go to the smaller id; fewer than k candidates give all.
Components are exact while floor(scale * x) stays within 2**31.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F, Window

LEVELS = 16
WAVES = 8


def quantise(vectors: DataFrame, id_col: str, vec_col: str, scale: int = 1024) -> DataFrame:
    """(vec_id long, ints array<long>) of the rows that take part."""
    v = F.col(vec_col)
    sound = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) != F.lit(float("inf"))))
    return vectors.where(F.col(id_col).isNotNull() & v.isNotNull() & sound).select(
        F.col(id_col).cast("long").alias("vec_id"), F.transform(v, lambda x: F.floor(x.cast("double") * scale).cast("long")).alias("ints")
    )


class ImpactBlock:
    """The posting segments of one block of integer vectors."""

    def __init__(self, ids, rows):
        import numpy as np

        self.ids, self.rows = ids, rows
        n, d = rows.shape
        top = int(np.abs(rows).max()) if rows.size else 0
        self.unit = max(1, -(-top // LEVELS))
        level = -(-np.abs(rows) // self.unit)  # 1..LEVELS; 0 has no posting
        key = (np.arange(d)[None, :] * (2 * LEVELS + 1)) + np.where(rows < 0, LEVELS + level, level)
        key[rows == 0] = -1
        flat = key.ravel()
        order = np.argsort(flat, kind="stable")
        order = order[flat[order] >= 0]
        keys, starts = np.unique(flat[order], return_index=True)
        self.posting = (order // d).astype(np.int32)
        self.start, self.stop = starts, np.r_[starts[1:], len(order)]
        self.dim = keys // (2 * LEVELS + 1)
        rest = keys % (2 * LEVELS + 1)
        self.level = np.where(rest > LEVELS, rest - LEVELS, rest)
        self.sign = np.where(rest > LEVELS, -1.0, 1.0)

    def search(self, query_id: int, q, k: int):
        """Positions and exact scores of the k best rows other than the query's own."""
        import numpy as np

        n, d = self.rows.shape
        own = self.ids == query_id
        weight = np.abs(q).astype(float)
        bound = weight[self.dim] * self.level * self.unit
        order = np.argsort(-bound, kind="stable")
        impact = q.astype(float)[self.dim] * self.sign * (self.level - 0.5) * self.unit
        rounding = 0.5 * self.unit * weight.sum()
        acc = np.zeros(n)
        acc[own] = -np.inf
        few = max(4 * k, 32)
        cuts = np.linspace(0, len(order), WAVES + 1).astype(int)
        members = np.flatnonzero(~own)
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            seg = order[a:b]
            if len(seg):
                size = self.stop[seg] - self.start[seg]
                begin = np.repeat(self.start[seg] - np.r_[0, np.cumsum(size)[:-1]], size)
                acc += np.bincount(self.posting[begin + np.arange(size.sum())], np.repeat(impact[seg], size), minlength=n)
            unseen = np.zeros(d)
            np.maximum.at(unseen, self.dim[order[b:]], bound[order[b:]])
            slack = 2 * (rounding + unseen.sum()) * (1 + 1e-9) + 1e-6
            if n > k:
                kth = np.partition(acc, n - k)[n - k]
                members = np.flatnonzero(acc >= kth - slack) if np.isfinite(kth) else np.flatnonzero(~own)
                members = members[~own[members]]
                if len(members) <= few:
                    break
        exact = self.rows[members] @ q
        best = np.lexsort((self.ids[members], -exact))[:k]
        return members[best], exact[best]


def _probe(k: int):
    def run(key, left, right):
        import numpy as np
        import pandas as pd

        out = {"query_id": [], "vec_id": [], "score": []}
        if len(left) and len(right):
            d = max(max(map(len, left.ints)), max(map(len, right.ints)), 1)

            def matrix(col):
                m = np.zeros((len(col), d), np.int64)
                for i, x in enumerate(col):
                    m[i, : len(x)] = x
                return m

            block = ImpactBlock(left.vec_id.to_numpy(np.int64), matrix(left.ints))
            for query_id, q in zip(right.vec_id.to_numpy(np.int64), matrix(right.ints), strict=True):
                at, score = block.search(query_id, q, k)
                out["query_id"] += [query_id] * len(at)
                out["vec_id"] += block.ids[at].tolist()
                out["score"] += score.tolist()
        return pd.DataFrame(out).astype({"query_id": "int64", "vec_id": "int64", "score": "int64"})

    return run


def top_k_inner_product(vectors: DataFrame, queries: DataFrame, k: int = 10, vector_block: int = 2048, query_block: int = 1024) -> DataFrame:
    """vectors, queries: (vec_id, ints). Returns query_id, rank, vec_id, score."""
    queries = queries.groupBy("vec_id").agg(F.min("ints").alias("ints"))
    n_v = max(1, -(-vectors.count() // vector_block))
    n_q = max(1, -(-queries.count() // query_block))
    deal = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    copies = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = vectors.withColumn("vb", deal(n_v)).withColumn("qb", copies(n_q))
    right = queries.withColumn("qb", deal(n_q)).withColumn("vb", copies(n_v))
    found = left.groupBy("vb", "qb").cogroup(right.groupBy("vb", "qb")).applyInPandas(_probe(k), "query_id long, vec_id long, score long")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
