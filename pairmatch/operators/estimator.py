"""The matcher as a pipeline stage, and functions for users of SQL."""

from __future__ import annotations

from pyspark.ml import Estimator, Model
from pyspark.ml.param.shared import Param, Params, TypeConverters
from pyspark.sql import DataFrame, SparkSession, functions as F

from pairmatch.operators.count_cloze import CountModel, evidence_list, tuned, with_evidence
from pairmatch.plans.dialect import spark_sql


class PairMatcher(Estimator):
    """Fits the counting cloze on rows with left_seq, right_seq and y; rows without y are only scored later.

    pretext: (word, f, n) counts of label-free pairs, or None.
    """

    template = Param(Params._dummy(), "template", "t1 or t2", TypeConverters.toString)

    def __init__(self, pretext: DataFrame | None = None, template: str = "t2"):
        super().__init__()
        self.pretext = pretext
        self._setDefault(template="t2")
        self._set(template=template)

    def _fit(self, dataset: DataFrame) -> PairMatcherModel:
        shape = self.getOrDefault(self.template)
        labelled = with_evidence(dataset.where("y is not null"), shape)
        none = dataset.sparkSession.createDataFrame([], "word int, f int, n bigint")
        return PairMatcherModel(tuned(self.pretext if self.pretext is not None else none, labelled), shape)


class PairMatcherModel(Model):
    def __init__(self, model: CountModel, shape: str):
        super().__init__()
        self.model, self.shape = model, shape

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return self.model.score(with_evidence(dataset, self.shape)).drop("ev")


def register(spark: SparkSession) -> None:
    """SQL functions token_jaccard(a, b) and cloze_evidence(a, b), and the table function explain_pair(a, b)."""
    tok = lambda c: spark_sql(f"KEEP(w, TOK({c}), w <> 'col' and w <> 'val')")
    spark.sql(f"create or replace temporary function token_jaccard(a string, b string) returns double return round(size(array_intersect({tok('a')}, {tok('b')})) / greatest(size(array_union({tok('a')}, {tok('b')})), 1), 6)")
    items = ", ".join(spark_sql(e) for e in evidence_list())
    spark.sql(f"create or replace temporary function cloze_evidence(a string, b string) returns array<int> return (select transform(array({items}), e -> cast(e as int)) from (select {tok('a')} as lt, {tok('b')} as rt))")

    @F.udtf(returnType="word string, in_left boolean, in_right boolean")
    class ExplainPair:
        """One row a word of either side."""

        def eval(self, a: str, b: str):
            import re

            left, right = (set(re.findall(r"[^\W_]+", (x or "").lower())) - {"col", "val"} for x in (a, b))
            for w in sorted(left | right):
                yield w, w in left, w in right

    spark.udtf.register("explain_pair", ExplainPair)
