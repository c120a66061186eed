import numpy as np

from pairmatch.functions import neural as N
from pairmatch.experiments import mean_f1
from pairmatch.operators.measures import prf
from pairmatch.operators.neural import NeuralLearner, NeuralModel, fit_allreduce, make, run_method
from pairmatch.operators.self_training import SelfTrainConfig, self_train
from tests.test_neural import rows

SPEC = {"net": {"dim": 8, "max_len": 24}}


def frame(spark, rs):
    return spark.createDataFrame([(r["pair_id"], r["left_seq"], r["right_seq"], r["y"]) for r in rs], "pair_id string, left_seq string, right_seq string, y int")


def test_scores_do_not_depend_on_partitions_and_bundles_reload(spark, tmp_path):
    df = frame(spark, rows(60, 1))
    model = NeuralLearner("cloze", SPEC, 2).fit(df)
    one = {r.pair_id: (r.p_yes, r.p_passes) for r in model.passes(model.score(df.coalesce(1)), 3).collect()}
    many = {r.pair_id: (r.p_yes, r.p_passes) for r in model.passes(model.score(df.repartition(5)), 3).collect()}
    assert one == many
    model.save(spark, str(tmp_path / "m"))
    again = NeuralModel.load(spark, str(tmp_path / "m")).score(df).collect()
    assert {r.pair_id: r.p_yes for r in again} == {k: v[0] for k, v in one.items()}


def test_gradients_summed_over_partitions_equal_one_batch(spark):
    rs = rows(24, 2)
    spread = fit_allreduce(frame(spark, rs).repartition(3), "head", SPEC, steps=2)
    local = make("head", SPEC).build()
    opt = N.T.AdamW(local.net.params, local.cfg.lr)
    for step in range(2):
        local.loss(rs, [r["pair_id"] for r in rs], step).backward()
        opt.step()
    for (name, _, got), (_, _, want) in zip(spread.tensors, local.bundle(), strict=True):
        assert np.allclose(got, want, atol=1e-6), name


def test_every_method_runs_and_hidden_truth_stays_hidden():
    part = {"label": rows(40, 1), "unlabel": rows(40, 2), "valid": rows(20, 3), "test": rows(40, 4), "source": rows(40, 5)}
    for m in ("proposed", "no_prompt", "attr_rnn", "meta_aug", "jaccard", "constant_yes"):
        got = run_method(m, part, SPEC | {"epochs": 2, "passes": 3})
        assert 0 <= got["f1"] <= 100
    flipped = part | {"unlabel": [r | {"y": 1 - r["y"]} for r in part["unlabel"]]}
    a, b = (run_method("proposed", p, SPEC | {"epochs": 2, "passes": 3}) for p in (part, flipped))
    assert a["f1"] == b["f1"]


def test_self_training_by_clusters_of_pair_vectors_around_another_method(spark):
    lab, un, valid = (frame(spark, rows(n, k)) for n, k in ((40, 1), (40, 2), (30, 3)))
    cfg = SelfTrainConfig(u_r=0.2, passes=3, selector="clustering", student_epochs=2, prune_every=4)
    for kind in ("siamese", "cloze"):
        best, log, last = self_train(NeuralLearner(kind, SPEC, 2), lab, un, valid, cfg)
        assert [x["rows"] for x in log.rows] == [40, 48, 48] and last.where("source = 'pseudo'").count() == 8
        assert prf(best.score(valid)).first()["f1"] == max(x["f1"] for x in log.rows if x["phase"] == "student")
        size = {len(r.vec) for r in best.vectors(valid).collect()}
        assert size == {24 if kind == "siamese" else 8}


def test_term_weights_choose_the_summary():
    w = N.term_weights(["a b", "a c", "a b d"])
    assert w["a"] == 0 and w["d"] > w["b"] > 0
    assert N.summarize("[COL] x a d b", w | {"x": 0.0}, 2) == "[COL] d b"


def test_mean_f1_over_workloads_and_differences(spark):
    found = spark.createDataFrame([("w1", "proposed", 80.0), ("w2", "proposed", 60.0), ("w1", "siamese", 50.0), ("w2", "siamese", 70.0)], "workload string, method string, f1 double")
    got = {r["method"]: (r["workloads"], r["mean_f1"], r["difference"]) for r in mean_f1(found).collect()}
    assert got == {"proposed": (2, 70.0, 0.0), "siamese": (2, 60.0, -10.0)}


def test_a_workload_is_sent_once_a_run_with_each_text_once(spark):
    from pairmatch.operators.neural import _pack, _unpack, run_experiments

    rs = [r | {"role": k, "workload": "w"} for k, n, seed in (("label", 20, 1), ("unlabel", 20, 2), ("valid", 10, 3), ("test", 20, 4)) for r in rows(n, seed)]
    df = spark.createDataFrame(rs, "workload string, pair_id string, left_seq string, right_seq string, y int, role string")
    one = [r | {"left_seq": "the same long text " * 50} for r in rs]
    data = _pack(spark.createDataFrame(one, df.schema).toArrow())
    assert data.count(b"the same long") <= 1 and len(data) < 30_000
    back = _unpack(data)
    assert back == sorted(({k: r[k] for k in ("pair_id", "left_seq", "right_seq", "y", "role")} for r in one), key=lambda r: r["pair_id"])
    assert len({id(r["left_seq"]) for r in back}) == 1
    runs = [{"run_id": f"r{i}", "workload": "w", "method": "jaccard", "setting": str(i), "spec": {}} for i in range(9)]
    found = run_experiments(df, runs)
    assert sorted(n for n in found.rdd.glom().map(len).collect() if n) == [1] * 9  # no two runs in one task
    by = {k: [r for r in rs if r["role"] == k] for k in ("label", "unlabel", "valid", "test", "source")}
    assert {round(r.f1, 9) for r in found.collect()} == {round(run_method("jaccard", by, {})["f1"], 9)}


def test_the_share_pruned_has_an_effect_in_every_run_of_the_grid(monkeypatch):
    from pairmatch import experiments as X

    found = []
    monkeypatch.setattr(X, "role_rows", lambda *a, **b: None)
    monkeypatch.setattr(X.M, "run_experiments", lambda rows, runs: found.extend(runs))
    X.grid(None, "")
    assert len(found) == 50
    part = {"label": rows(40, 1), "unlabel": rows(40, 2), "valid": rows(10, 3), "test": rows(10, 4)}
    spent = lambda e, spec: run_method("proposed", part, {"net": {"dim": 4, "max_len": 24}, "passes": 2, "e_r": e} | spec)["example_epochs"]
    of_grid = {k: v for k, v in found[0]["spec"].items() if k in ("epochs", "every")}
    for spec in (of_grid, {"epochs": 4}):
        got = [spent(e, spec) for e in (0.1, 0.3, 0.5)]
        assert got == sorted(got, reverse=True) and len(set(got)) == 3


def test_runs_share_a_teacher_that_many_tasks_ask_and_find_what_each_found_alone(spark, monkeypatch):
    from pairmatch.operators import neural as M

    monkeypatch.setattr(M, "SCORED_ROWS", 7)
    def run(runs, frames):
        return {r.run_id: r for r in M.run_experiments(frames, runs).collect()}

    by = {"label": rows(30, 1), "unlabel": rows(40, 2), "valid": rows(20, 3), "test": rows(30, 4), "source": []}
    frames = spark.createDataFrame([r | {"role": k, "workload": "w"} for k, rs in by.items() for r in rs], "workload string, pair_id string, left_seq string, right_seq string, y int, role string")
    spec = {"net": {"dim": 4, "max_len": 24}, "epochs": 2, "passes": 2}
    cases = [("proposed", {}), ("proposed", {"e_r": 0.5}), ("no_pruning", {"selector": "clustering"}), ("no_self_training", {}), ("no_prompt", {"u_r": 0.3})]
    runs = [{"run_id": str(i), "workload": "w", "method": m, "setting": "", "spec": spec | x} for i, (m, x) in enumerate(cases)]
    order = {k: sorted(v, key=lambda r: r["pair_id"]) for k, v in by.items()}
    found = run(runs, frames)
    for r in runs:
        want = run_method(r["method"], order, r["spec"])
        assert found[r["run_id"]].f1 == want["f1"] and (r["method"] == "no_self_training" or found[r["run_id"]].example_epochs == want["example_epochs"])
    taught = M._taught
    asked = []
    monkeypatch.setattr(M, "_taught", lambda rows, packs, runs, of, teachers: asked.append((of, len(teachers))) or taught(rows, packs, runs, of, teachers))
    M.run_experiments(frames, runs)
    assert asked == [([0, 0, 0, 0, 1], 2)]


def test_cells_in_one_node_are_those_of_many():
    rng, T = np.random.default_rng(3), N.T
    for make_, sides in ((lambda a, w, u: T.lstm(a, w, u, True), ((5, 4), (4, 12), (3, 12))), (lambda a, w, u: T.gru(a, np.array([[1.0, 1, 0], [1, 0, 0]]), w, u), ((2, 3, 4), (4, 12), (4, 12)))):
        vs = [T.Var(rng.normal(size=s)) for s in sides]
        out = make_(*vs)
        weight = rng.normal(size=out.v.shape)
        T.total(out * weight).backward()
        for v in vs:
            for i in [tuple(rng.integers(s) for s in v.v.shape) for _ in range(6)]:
                at, h = v.v[i], 1e-6
                v.v[i] = at + h
                up = (make_(*vs).v * weight).sum()
                v.v[i] = at - h
                down = (make_(*vs).v * weight).sum()
                v.v[i] = at
                assert abs(v.grad[i] - (up - down) / (2 * h)) < 1e-6
