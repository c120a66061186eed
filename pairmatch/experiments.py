"""The experiments re-expressed: each is a list of runs, every run one task."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pairmatch.operators import graph_walk as G, measures as Q, neural as M, self_training as S
from pairmatch.plans.session import cut
from pairmatch.sources import workloads as W


def role_rows(spark: SparkSession, d: str, w: str, rate: float | None = None, count: int | None = None, source: str | None = None) -> DataFrame:
    """All pairs of a workload with texts and their role at a label rate or count; source adds another workload's labels."""
    left, right = W.sequences(spark, d, w)
    p = cut(W.attach(W.pairs(spark, d, w), left, right).select("pair_id", "left_seq", "right_seq", "y", "split"))
    lab, _ = S.take_labels(p.where("split = 'train'"), p.count(), rate if count is None else None, count)
    marked = p.join(lab.select("pair_id", F.lit(1).alias("_l")), "pair_id", "left")
    role = F.when(F.col("_l") == 1, "label").when(F.col("split") == "train", "unlabel").otherwise(F.col("split"))
    out = marked.select(F.lit(w).alias("workload"), "pair_id", "left_seq", "right_seq", "y", role.alias("role"))
    if source:
        other = role_rows(spark, d, source, W.DEFAULT_RATE[source]).where("role = 'label'")
        out = out.unionByName(other.select(F.lit(w).alias("workload"), F.concat(F.lit("s|"), "pair_id").alias("pair_id"), "left_seq", "right_seq", "y", F.lit("source").alias("role")))
    return out


def runs(w: str, methods, setting: str, spec: dict | None = None) -> list[dict]:
    return [{"run_id": f"{w}:{m}:{setting}", "workload": w, "method": m, "setting": setting, "spec": spec or {}} for m in methods]


def walk_results(spark, d, w: str, roles: DataFrame, setting: str) -> DataFrame:
    """Rows of the result table for walks without labels and for the network on their vectors, which learns from the label rows."""
    began, none = time.time(), F.lit(float("nan"))
    left, right = W.sequences(spark, d, w)
    found = cut(G.match(left, right, W.pairs(spark, d, w)).join(roles.select("pair_id", "role"), "pair_id"))
    out = None
    for method, scored in (("graph_walk", found), ("graph_walk_mlp", cut(G.match_mlp(found)))):
        cost = [none.alias("tpr"), none.alias("tnr"), F.lit(time.time() - began).alias("seconds"), none.alias("example_epochs"), F.lit(Q.peak_memory_mb()).alias("peak_mb")]
        names = [F.lit(f"{w}:{method}:{setting}").alias("run_id"), F.lit(w).alias("workload"), F.lit(method).alias("method"), F.lit(setting).alias("setting")]
        one = Q.prf(scored.where("role = 'test'")).select(*names, "precision", "recall", "f1", *cost)
        out = one if out is None else out.unionByName(one)
    return out


def main_comparison(spark, d, w="w6", methods=M.METHODS, source="w8", walks=True):
    """Default label rate, all methods (the table of the main comparison)."""
    rows, setting = cut(role_rows(spark, d, w, W.DEFAULT_RATE[w], source=source if source != w else "w4")), f"rate {W.DEFAULT_RATE[w]}"
    found = M.run_experiments(rows, runs(w, methods, setting))
    return found.unionByName(walk_results(spark, d, w, rows, setting)) if walks else found


def over_workloads(spark, d, ws=tuple(W.DEFAULT_RATE), methods=M.METHODS, walks=True):
    """The main comparison over several workloads."""
    out = None
    for w in ws:
        one = main_comparison(spark, d, w, methods, walks=walks)
        out = one if out is None else out.unionByName(one)
    return out


def mean_f1(results: DataFrame, to: str = "proposed") -> DataFrame:
    """method, workloads, mean_f1 over workloads, and its difference from one method's."""
    mean = results.groupBy("method").agg(F.count("*").alias("workloads"), F.round(F.avg("f1"), 4).alias("mean_f1"))
    other = F.max(F.when(F.col("method") == to, F.col("mean_f1"))).over(Window.partitionBy(F.lit(0)))  # a row a method
    return mean.withColumn("difference", F.round(F.col("mean_f1") - other, 4))


def few_labels(spark, d, w="w6"):
    """A fixed count of 80 labels."""
    rows = cut(role_rows(spark, d, w, count=80, source="w8"))
    return M.run_experiments(rows, runs(w, M.METHODS, "80 labels")).unionByName(walk_results(spark, d, w, rows, "80 labels"))


def label_rates(spark, d, w="w6", methods=("proposed", "pair_lm", "siamese")):
    """F1 against the label rate, 5 to 25 per cent."""
    rows, rs = None, []
    for r in (0.05, 0.10, 0.15, 0.20, 0.25):
        one = role_rows(spark, d, w, r).withColumn("workload", F.lit(f"{w} {r}"))
        rows = one if rows is None else rows.unionByName(one)
        rs += [x | {"rows": f"{w} {r}"} for x in runs(w, methods, f"rate {r}")]
    return M.run_experiments(rows, rs)


def ablations(spark, d, w="w6"):
    return M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), runs(w, ("proposed", "no_prompt", "no_self_training", "no_pruning"), "ablation"))


def efficiency(spark, d, w="w6"):
    """Seconds, memory and example-epochs of training."""
    return M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), runs(w, ("siamese", "meta_aug", "no_pruning", "proposed"), "cost"))


def templates(spark, d, w="w6"):
    """Two shapes, literal and learned."""
    rs = [r for s in ("t1", "t2") for k in ("hard", "soft") for r in runs(w, ("no_self_training",), f"{k} {s}", {"shape": s, "template": k})]
    return M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), rs)


def label_words(spark, d, w="w6"):
    """General against simple label words, for both learned templates."""
    rs = [r for s in ("t1", "t2") for k in ("general", "simple") for r in runs(w, ("no_self_training",), f"{k} {s}", {"shape": s, "words": k})]
    return M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), rs)


def selectors(spark, d, w="w6"):
    """Pseudo-label quality of four ways to pick a tenth."""
    rs = [r for k in ("uncertainty", "confidence", "clustering", "random") for r in runs(w, ("no_pruning",), k, {"selector": k, "u_r": 0.1})]
    return M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), rs)


def grid(spark, d, w="w6", u=(0.05, 0.10, 0.15, 0.20, 0.25), e=(0.1, 0.2, 0.3, 0.4, 0.5)):
    """Template x share of pseudo-labels x share pruned, with all reported epochs, so that each run prunes three times."""
    rs = [r for s in ("t1", "t2") for a in u for b in e for r in runs(w, ("proposed",), f"{s} u={a} e={b}", {"shape": s, "u_r": a, "e_r": b})]
    return M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), rs)


def digits(spark, d):
    """Share of numeric values by workload: see numeric_value_share; here with the overlap floor's F1."""
    out = None
    for w in ("w1", "w8"):
        one = M.run_experiments(role_rows(spark, d, w, W.DEFAULT_RATE[w]), runs(w, ("jaccard",), "digits"))
        out = one if out is None else out.unionByName(one)
    return out


def walk_growth(spark, d, w="w6"):
    """Rows that walks of growing length make."""
    g = cut(G.edges(*W.sequences(spark, d, w)))
    found = cut(G.walks(g, per_node=4, length=6))
    return found.groupBy("step").agg(F.count("*").alias("rows"), F.countDistinct("node").alias("nodes"))


def queries() -> dict:
    fs = (main_comparison, few_labels, label_rates, ablations, efficiency, templates, label_words, selectors, grid, digits, walk_growth)
    return {f"exp_{f.__name__}": f for f in fs}
