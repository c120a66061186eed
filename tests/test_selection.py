import hashlib
import random

from pyspark.sql import functions as F

from pairmatch.operators import measures as Q, self_training as S
from pairmatch.plans import bottomk


def tie(i):
    return int(hashlib.md5(("tie|" + i).encode()).hexdigest()[:8], 16)


def test_bottom_k_with_ties_by_limit_and_by_histogram(spark, monkeypatch):
    rng = random.Random(5)
    rows = [(f"p{i}", rng.choice([0, 1, 7, 900_000, 10**9])) for i in range(5000)]
    df = spark.createDataFrame(rows, "pair_id string, s long").cache()
    order = [i for _, _, i in sorted((s, tie(i), i) for i, s in rows)]
    for small in (100_000, 10):
        monkeypatch.setattr(bottomk, "SMALL", small)
        for k in (1, 17, 2500, 5000):
            low, rest = bottomk.split_bottom(df, "s", "pair_id", k)
            assert {r.pair_id for r in low.collect()} == set(order[:k])
            assert rest.count() == 5000 - k
    assert bottomk.split_bottom(df, "s", "pair_id", 0)[0].count() == 0


def test_uncertainty_norms_and_rates(spark):
    df = spark.createDataFrame([("a", 1, [0.5, 0.7]), ("b", 0, [0.2, 0.2])], "pair_id string, y int, p_passes array<double>")
    u = {r.pair_id: r.u for r in S.uncertainty(df, 2).collect()}
    assert u == {"a": 0.1, "b": 0.0}
    e = {r.pair_id: r.e for r in S.mc_el2n(df, 2).collect()}
    assert e == {"a": round(2**0.5 * 0.4, 6), "b": round(2**0.5 * 0.2, 6)}
    assert [S.share(n, r) for n, r in ((10, 0.1), (9, 0.1), (30, 0.3))] == [1, 0, 9]


def test_measures_with_empty_denominators(spark):
    df = spark.createDataFrame([(1, 0), (0, 0)], "y int, pred int")
    r = Q.prf(df).first()
    assert (r.tp, r.precision, r.recall, r.f1) == (0, 0.0, 0.0, 0.0)
    t = Q.tpr_tnr(df.where("y = 0").withColumn("pseudo", F.col("pred"))).first()
    assert t.tpr is None and t.tnr == 1.0
    q = 0.7
    assert abs(Q.example_epochs(100_000, 0.3) / 100_000 - (8 + 8 * q + 8 * q * q + 6 * q**3)) < 1e-3


def test_loop_keeps_set_algebra(spark):
    import pairmatch.operators.count_cloze as K

    rng = random.Random(3)
    row = lambda i: (f"{i}|x", [rng.randrange(10), 16 + rng.randrange(10), 32 + rng.randrange(10), 48, 64, 80 + rng.randrange(3)], rng.randrange(2))
    rows = spark.createDataFrame([row(i) for i in range(260)], "pair_id string, ev array<int>, y int").withColumn("n", F.expr("cast(split(pair_id, '[|]')[0] as int)"))
    lab, un, valid = rows.where("n < 60").drop("n"), rows.where("n between 60 and 199").drop("n", "y"), rows.where("n >= 200").drop("n")
    pre = spark.createDataFrame([(w, f, 3) for w in range(6) for f in (0, 16, 32, 48, 64, 80)], "word int, f int, n long")
    model, log, last = S.self_train(S.CountTeacher(pre), lab, un, valid, S.SelfTrainConfig(u_r=0.1, e_r=0.2))
    sizes = [x["rows"] for x in log.rows if x["phase"] in ("selected", "pruned")]
    assert sizes == [74, 74 - 14, 60 - 12, 48 - 9]
    ids = {r.pair_id for r in last.collect()}
    assert not ids & {r.pair_id for r in valid.collect()}
    assert isinstance(model, K.CountModel)


def test_evidence_from_record_features_is_that_of_pairs(spark):
    """Tokens are cut below the joins, once a record, and give what each pair's texts gave."""
    import random

    from pairmatch.operators import count_cloze as K

    rng = random.Random(5)
    words = ["col", "val", "12", "345.50", "a1b2c3", "Straße", "red", "crimson", "x", "x", "ok-go", "ÉTÉ", "日本語テキスト"]
    texts = ["", None, "col val", "12", "red red red", *(" ".join(rng.choices(words, k=rng.randrange(1, 9))) for _ in range(12))]
    side = spark.createDataFrame([(str(i), t) for i, t in enumerate(texts)], "id string, seq string")
    pairs = spark.createDataFrame([(f"{i}|{j}", str(i), str(j)) for i in range(len(texts)) for j in range(len(texts))], "pair_id string, left_id string, right_id string")
    for template in ("t1", "t2"):
        got = K.evidence_of(pairs, side, side, template)
        plan = got._jdf.queryExecution().optimizedPlan().toString()
        assert "lower(" not in plan.split("Join")[0]
        both = pairs.join(side.select(F.col("id").alias("left_id"), F.col("seq").alias("left_seq")), "left_id").join(side.select(F.col("id").alias("right_id"), F.col("seq").alias("right_seq")), "right_id")
        want = {r.pair_id: r.ev for r in K.with_evidence(both, template).collect()}
        assert {r.pair_id: r.ev for r in got.collect()} == want and len(want) == len(texts) ** 2


def test_passes_leave_out_by_the_digits_of_the_hash(spark):
    import hashlib
    import math
    import random

    from pairmatch.operators import count_cloze as K

    rng = random.Random(6)
    model = K.CountModel(tuple(tuple(rng.randrange(-9_000_000, 0) for _ in range(K.EVIDENCE)) for _ in K.WORDS), tuple(range(-6, 0)), K.Verbalizer.general())
    rows = [(f"p{i}", [rng.randrange(0, 3) + 16 * k for k in range(6)]) for i in range(40)]
    got = {r.pair_id: list(r.p_passes) for r in model.passes(spark.createDataFrame(rows, "pair_id string, ev array<int>")).collect()}
    for pair, ev in rows:
        for k in range(10):
            h = hashlib.md5(f"drop0|{pair}|{k}".encode()).hexdigest()
            s = [model.prior[w] + sum(model.weights[w][e] for i, e in enumerate(ev) if int(h[i], 16) >= 5) for w in range(6)]
            q = [math.exp((x - max(s)) / 1e6) for x in s]
            yes, no = sum(q[:3]) / 3, sum(q[3:]) / 3
            assert abs(got[pair][k] - yes / (yes + no)) < 1.1e-6


def test_records_and_passes_take_one_look_at_a_token_and_short_code(spark):
    """A token is asked for digits once, pairs split no text, and a pass is one short expression: long ones are not compiled."""
    from pairmatch.operators import count_cloze as K

    side = spark.createDataFrame([("1", "a1 b red"), ("2", "red crimson")], "id string, seq string")
    pairs = spark.createDataFrame([("1|2", "1", "2")], "pair_id string, left_id string, right_id string")
    plan = K.evidence_of(pairs, side, side)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("[0-9]") == 2  # once a side
    assert "split(left" not in plan and "split(right" not in plan
    model = K.CountModel(tuple((-1,) * K.EVIDENCE for _ in K.WORDS), (-1,) * 6, K.Verbalizer.general())
    passes = model.passes(K.evidence_of(pairs, side, side))
    assert passes._jdf.queryExecution().optimizedPlan().toString().count("shiftright") == 0
    assert len(passes.first()["p_passes"]) == 10


def test_evidence_is_made_in_parts_and_is_that_of_all(spark, monkeypatch):
    from pairmatch.operators import count_cloze as K
    from pairmatch.plans.session import put_down

    texts = spark.range(60).selectExpr("cast(id as string) id", "concat('[COL] a [VAL] w', id % 7, ' x', id % 5, ' longword', id % 3, ' ', id) seq")
    pairs = texts.selectExpr("id as left_id").crossJoin(texts.selectExpr("id as right_id")).selectExpr("left_id", "right_id", "left_id || '|' || right_id as pair_id")
    want = sorted((r.pair_id, r.ev) for r in K.evidence_of(pairs, texts, texts).collect())
    monkeypatch.setattr(K, "PART_PAIRS", 500)
    written = []
    monkeypatch.setattr(K, "put_down", lambda df, name: written.append((name, put_down(df, name))) or written[-1][1])
    got = K.stored_evidence(pairs, texts, texts, ["pair_id"])
    assert sorted((r.pair_id, r.ev) for r in got.collect()) == want and len(want) == 3600
    sizes = [x.count() for name, x in written if name == "evidence"]
    assert len(sizes) == 8 and max(sizes) < 1200
