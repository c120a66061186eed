"""Pseudo-label selection, training-set pruning, and the loop around them.

Selectors and pruners see scored tables only, so that any model with pass-wise
predictions can be wrapped. Hidden truth is never a column of what the trainer sees.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window, functions as F

from pairmatch.operators.count_cloze import CountModel, tuned
from pairmatch.plans.bottomk import split_bottom, tie
from pairmatch.plans.session import cut


def micro(c: Column) -> Column:
    return F.round(c * 1_000_000).cast("long")


def _unrolled(arr: str, n: int, f) -> Column:
    cells = [f(F.col(arr)[i]) for i in range(n)]
    total = cells[0]
    for c in cells[1:]:
        total = total + c
    return total


def uncertainty(passes: DataFrame, n: int = 10) -> DataFrame:
    """Adds u: population standard deviation of the passes' P(yes), 6 digits; and u_micro."""
    mean = _unrolled("p_passes", n, lambda c: c) / n
    with_mean = passes.withColumn("p_mean", mean)
    var = _unrolled("p_passes", n, lambda c: (c - F.col("p_mean")) * (c - F.col("p_mean"))) / n
    return with_mean.withColumn("u", F.round(F.sqrt(var), 6)).withColumn("u_micro", micro(F.col("u"))).withColumn("p_mean", F.round("p_mean", 6))


def el2n(scored: DataFrame) -> DataFrame:
    """Adds e: norm of the class vector minus the label's, dropout off."""
    return scored.withColumn("e", F.round(F.sqrt(F.lit(2.0)) * F.abs(F.col("y") - F.col("p_yes")), 6)).withColumn("e_micro", micro(F.col("e")))


def mc_el2n(passes: DataFrame, n: int = 10) -> DataFrame:
    """Adds e: mean over passes of the norm of the class vector minus the label's."""
    mean = _unrolled("p_passes", n, lambda c: F.abs(F.col("y") - c)) / n
    return passes.withColumn("e", F.round(F.sqrt(F.lit(2.0)) * mean, 6)).withColumn("e_micro", micro(F.col("e")))


def share(n: int, rate: float) -> int:
    """Rows that a rate of n is: rounded down."""
    return int(n * rate + 1e-9)


def take_labels(train: DataFrame, n_all: int, rate: float | None = None, count: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(labelled, unlabelled without y): a fixed count, or a rate of all labelled pairs rounded half up; nested across rates."""
    k = count if count is not None else int(n_all * rate + 0.5)
    order = train.withColumn("lab_h", F.expr("cast(conv(substr(md5('lab|' || pair_id), 1, 8), 16, 10) as bigint)"))
    lab, rest = split_bottom(order, "lab_h", "pair_id", k)
    return lab.drop("lab_h"), rest.drop("lab_h", "y")


def select_uncertainty(scored: DataFrame, u_r: float, balance: str = "none") -> tuple[DataFrame, DataFrame]:
    """(chosen, rest): the share u_r of rows with the least uncertainty; scored has u_micro and pseudo."""
    if balance == "per_class":
        return select_balanced(scored, u_r)
    return split_bottom(scored, "u_micro", "pair_id", share(scored.count(), u_r))


def select_confidence(scored: DataFrame, rate: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """The share of rows whose best class is most probable."""
    ranked = scored.withColumn("nc", -micro(F.greatest(F.col("p_yes"), 1 - F.col("p_yes"))))
    a, b = split_bottom(ranked, "nc", "pair_id", share(scored.count(), rate))
    return a.drop("nc"), b.drop("nc")


def select_random(scored: DataFrame, rate: float = 0.1) -> tuple[DataFrame, DataFrame]:
    ranked = scored.withColumn("nr", F.expr("cast(conv(substr(md5('rand|' || pair_id), 1, 8), 16, 10) as bigint)"))
    a, b = split_bottom(ranked, "nr", "pair_id", share(scored.count(), rate))
    return a.drop("nr"), b.drop("nr")


def select_all(scored: DataFrame, rate: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """The costly form: every unlabelled row with the teacher's label."""
    return scored, scored.limit(0)


def select_balanced(scored: DataFrame, rate: float) -> tuple[DataFrame, DataFrame]:
    """The least uncertain share of each predicted class."""
    parts = [select_uncertainty(scored.where(F.col("pseudo") == c), rate) for c in (0, 1)]
    return parts[0][0].unionByName(parts[1][0]), parts[0][1].unionByName(parts[1][1])


def select_clustering(scored: DataFrame, rate: float = 0.1, k: int = 2, seed: int = 7, vector: str = "vec") -> tuple[DataFrame, DataFrame]:
    """Rows nearest to their k-means centre; their pseudo-label is the cluster's majority."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v = scored.withColumn("_v", array_to_vector(F.col(vector).cast("array<double>")))
    model = KMeans(k=k, seed=seed, featuresCol="_v", predictionCol="_c").fit(v)
    centres = F.array(*[F.array(*[F.lit(float(x)) for x in c]) for c in model.clusterCenters()])
    at = model.transform(v).withColumn("_a", vector_to_array("_v")).drop("_v")
    dist = F.aggregate(F.zip_with("_a", F.get(centres, F.col("_c")), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    at = at.withColumn("_d", micro(F.sqrt(dist)))
    major = at.groupBy("_c").agg((F.avg("pseudo") > 0.5).cast("int").alias("_m"))
    near = cut(at.join(F.broadcast(major), "_c").withColumn("pseudo", F.col("_m")).drop("_a", "_m", "_c"))  # k rows are broadcast
    a, b = split_bottom(near, "_d", "pair_id", share(near.count(), rate))
    return a.drop("_d"), b.drop("_d")


def prune(train: DataFrame, e_r: float) -> tuple[DataFrame, DataFrame]:
    """(kept, dropped): the share e_r of rows with the least importance leaves; train has e_micro."""
    gone, kept = split_bottom(train, "e_micro", "pair_id", share(train.count(), e_r))
    return kept, gone


@dataclass
class SelfTrainConfig:
    """Defaults as reported: one iteration, ten passes, pruning every 8 of 30 student epochs."""

    u_r: float = 0.10
    e_r: float = 0.20
    iters: int = 1
    passes: int = 10
    teacher_epochs: int = 20
    student_epochs: int = 30
    prune_every: int = 8
    selector: str = "uncertainty"
    pruning: bool = True
    pseudo_from: str = "eval"
    keep_best_of: str = "student"

    def prunes(self) -> int:
        return sum(1 for e in range(1, self.student_epochs) if e % self.prune_every == 0) if self.pruning else 0


SELECTORS = {"uncertainty": select_uncertainty, "confidence": select_confidence, "random": select_random, "balanced": select_balanced, "all": select_all, "clustering": select_clustering}


@dataclass
class RunLog:
    rows: list[dict] = field(default_factory=list)

    def add(self, **x) -> None:
        self.rows.append(x)


class CountTeacher:
    """The counting backbone as a trainable model: fit counts, predict, predict with dropout."""

    def __init__(self, pretext: DataFrame, verb=None):
        self.pretext, self.verb = pretext, verb

    def fit(self, train: DataFrame) -> CountModel:
        return tuned(self.pretext, train, self.verb)


def self_train(learner, labelled: DataFrame, unlabelled: DataFrame, valid: DataFrame, cfg: SelfTrainConfig | None = None):
    """(best model, log, last training set). labelled and valid have pair_id, the
    learner's columns and y; unlabelled the same without y.

    learner.fit(train) gives a model with score(df) and passes(df, n): see CountTeacher
    and operators.neural for two such learners.
    """
    from pairmatch.operators.measures import prf

    cfg, log, best = cfg or SelfTrainConfig(), RunLog(), None
    cols = tuple(getattr(learner, "columns", ("ev",)))
    labelled = cut(labelled.select("pair_id", *cols, "y").withColumn("source", F.lit("label")))
    unlabelled = cut(unlabelled.select("pair_id", *cols))
    f1 = lambda m: prf(m.score(valid)).first()["f1"]
    for it in range(max(1, cfg.iters)):
        teacher = learner.fit(labelled)
        log.add(iter=it, phase="teacher", rows=labelled.count(), f1=f1(teacher))
        if cfg.keep_best_of == "teacher_or_student" or cfg.iters == 0:
            best = max([x for x in (best, (log.rows[-1]["f1"], teacher)) if x], key=lambda x: x[0])
        if cfg.iters == 0:
            return best[1], log, labelled
        scored = uncertainty(teacher.passes(teacher.score(unlabelled), cfg.passes), cfg.passes)
        label = F.col("pred") if cfg.pseudo_from == "eval" else (F.col("p_mean") > 0.5).cast("int")
        vec = ()
        if cfg.selector == "clustering":  # a model without vectors of its own is clustered by its passes
            scored, vec = teacher.vectors(scored) if hasattr(teacher, "vectors") else scored.withColumn("vec", F.col("p_passes")), ("vec",)
        scored = cut(scored.withColumn("pseudo", label).select("pair_id", *cols, "p_yes", "u", "u_micro", "pseudo", *vec))
        chosen, unlabelled = SELECTORS[cfg.selector](scored, cfg.u_r)
        unlabelled = unlabelled.select("pair_id", *cols)
        labelled = cut(labelled.unionByName(chosen.select("pair_id", *cols, F.col("pseudo").alias("y"), F.lit("pseudo").alias("source"))))
        log.add(iter=it, phase="selected", rows=labelled.count(), f1=None)
        student = learner.fit(labelled)
        for _ in range(cfg.prunes()):
            ranked = cut(mc_el2n(student.passes(labelled, cfg.passes), cfg.passes))
            kept, _gone = prune(ranked, cfg.e_r)
            labelled = cut(kept.select("pair_id", *cols, "y", "source"))
            student = learner.fit(labelled)
            log.add(iter=it, phase="pruned", rows=labelled.count(), f1=f1(student))
        log.add(iter=it, phase="student", rows=labelled.count(), f1=f1(student))
        best = max([x for x in (best, (log.rows[-1]["f1"], student)) if x], key=lambda x: x[0])
    return best[1], log, labelled
