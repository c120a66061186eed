"""Quality by compression: which of two trained dictionaries shortens a text more.

A zstandard dictionary is trained on good and another on bad labelled text. A text
is cut into chunks, each compressed with either dictionary; the difference of the
summed sizes over the text's bytes is turned into a score by logistic calibration
on labelled rows that trained no dictionary.

The labelled rows used are at most `per_class` of each class (the lowest by hash of the
id); of the longer ones `parts` pieces, dealt evenly from first to last, so that the
sample has a bound; scoring reads whole texts.

Defined results: null and empty texts score the calibration's value at difference 0;
null labels and labels without a document are not used; with one class or none the
score is constant; repeated rows are scored each, alike; an empty table gives no row;
texts of any length are read whole, chunk by chunk.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.llm.common import fit_logistic, sigmoid, stored

CHUNK = 2048
DICTIONARY = 110 * 1024
PIECE = 2048
SHRINK = 128  # bytes added to a text's length, so that short texts need more evidence
LEVEL = 3


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, learn: Column, per_class: int, parts: int) -> list:
    """[([pieces of a text], 0 or 1)] of at most per_class rows of either class, chosen by hash.

    Texts of more than `parts` pieces of PIECE characters give that many, dealt evenly
    from their first to their last: what the driver gets is bounded, and no part of a
    text is beyond the reach of fitting.
    """
    picked = labels.where(learn & F.col("doc_id").isNotNull()).select("doc_id", F.col(label).alias("y"), F.xxhash64(F.lit("sample"), F.col("doc_id")).alias("n"))
    lowest = [picked.where(F.col("y") == y).orderBy("n", "doc_id").limit(per_class) for y in (0, 1)]
    chosen = stored(lowest[0].unionByName(lowest[1]), "labelled-sample")  # 2 x per_class rows
    n = f"int(ceil(length(text) / {PIECE}))"
    at = f"if({n} <= {parts}, sequence(0, greatest({n} - 1, 0)), transform(sequence(0, {parts - 1}), i -> int(round(i * ({n} - 1) / {max(parts - 1, 1)}))))"
    pieces = F.expr(f"transform({at}, i -> substr(text, 1 + i * {PIECE}, {PIECE}))")
    held = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    rows = held.select("doc_id", pieces.alias("pieces"), F.xxhash64("text").alias("th")).join(F.broadcast(chosen), "doc_id").collect()
    return [(r["pieces"], r["y"]) for r in sorted(rows, key=lambda r: (r["n"], r["y"], r["th"]))]


def chunks(data: bytes):
    return [data[i : i + CHUNK] for i in range(0, len(data), CHUNK)]


class TwoDictionaries:
    def __init__(self, good: bytes, bad: bytes, weight: float = 0.0, bias: float = 0.0):
        self.good, self.bad, self.weight, self.bias = good, bad, weight, bias

    def compressors(self):
        import zstandard as z

        make = lambda d: z.ZstdCompressor(level=LEVEL, dict_data=z.ZstdCompressionDict(d), write_content_size=False, write_checksum=False, write_dict_id=False)
        return make(self.good), make(self.bad)

    @staticmethod
    def difference(data: bytes, good, bad) -> float:
        """Bytes saved by the good dictionary over the bad one, by the text's length."""
        if not data:
            return 0.0
        parts = chunks(data)
        return (sum(len(bad.compress(p)) for p in parts) - sum(len(good.compress(p)) for p in parts)) / (len(data) + SHRINK)

    def score(self, difference):
        return sigmoid(self.weight * difference + self.bias)


def _train(texts: list[list[str]]) -> bytes:
    import zstandard as z

    parts = [c for t in texts for c in chunks("".join(t).encode())]
    try:
        return z.train_dictionary(DICTIONARY, parts).as_bytes()
    except z.ZstdError:  # too little text to train on: the text itself is the dictionary
        return b"".join(parts)[-DICTIONARY:] or b"\0" * 8


def fit(sample: list, odds: float = 1.0) -> TwoDictionaries:
    """odds: how many rows of label 1 there are for one of label 0, beyond the sample."""
    import numpy as np

    by = {y: [t for t, v in sample if v == y] for y in (0, 1)}
    shape = {y: v[: (2 * len(v) + 2) // 3] for y, v in by.items()}
    model = TwoDictionaries(_train(shape[1]), _train(shape[0]))
    held = [(t, y) for y in (0, 1) for t in by[y][len(shape[y]) :]]
    good, bad = model.compressors()
    x = np.array([model.difference("".join(t).encode(), good, bad) for t, _ in held])
    w, model.bias = fit_logistic(x, np.array([y for _, y in held])) if held else (np.zeros(1), 0.0)
    model.weight = float(w[0])
    if model.weight:
        model.bias += math.log(odds)
    return model


def score_documents(docs: DataFrame, model: TwoDictionaries) -> DataFrame:
    """doc_id, difference, score of every document."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        good, bad = model.compressors()
        for batch in batches:
            x = np.array([model.difference((t.as_py() or "").encode(), good, bad) for t in batch.column(1)], float)
            yield pa.record_batch([batch.column(0), pa.array(x), pa.array(model.score(x))], names=["doc_id", "difference", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, difference double, score double")


def quality_scores(docs: DataFrame, labels: DataFrame, learn: Column, per_class: int = 4000, parts: int = 4) -> DataFrame:
    n = labels.where(learn).agg(F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("quality") == 0).alias("bad")).first()
    odds = n["good"] / n["bad"] if n["good"] and n["bad"] else 1.0
    return score_documents(docs, fit(labelled_sample(docs, labels, "quality", learn, per_class, parts), odds))
