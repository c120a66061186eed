"""All library queries and their SQL twins, by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from pairmatch import oracles as O
from pairmatch.functions.serialize import encode_pair, truncate_pair
from pairmatch.functions.templates import Template, Verbalizer
from pairmatch.operators import count_cloze as K, measures as Q, self_training as S
from pairmatch.plans.session import cut
from pairmatch.sources import workloads as W

KEYED = tuple(W.SIDES)


def pair_rows(spark, d, w):
    return W.pairs(spark, d, w).select("pair_id", "y", "split")


IN_PARTS = ("w3",)  # long records, whose tokens fill the disk where all pairs take them along at once


def evidence_rows(spark, d, w, template="t2"):
    """Pairs of a workload with their evidence, stored."""
    left, right = W.sequences(spark, d, w)
    if w in IN_PARTS:
        return K.stored_evidence(W.pairs(spark, d, w), left, right, ["pair_id", "y", "split"], template)
    return cut(K.evidence_of(W.pairs(spark, d, w), left, right, template).select("pair_id", "y", "split", "ev"))


def setting(spark, d, w, rate=None, verb=None):
    """(all pairs with evidence, labelled, unlabelled, pretext counts) of a workload at its label rate."""
    ev = evidence_rows(spark, d, w)
    train = ev.where("split = 'train'")
    lab, un = S.take_labels(train, ev.count(), rate if rate is not None else W.DEFAULT_RATE[w])
    return ev, lab, un, cut(K.pretext_counts(spark, d))


def predicted(spark, d, w):
    ev, lab, _, pre = setting(spark, d, w)
    return K.tuned(pre, lab).score(ev).select("pair_id", "y", "split", "p_yes", "pred")


def unlabelled_scored(spark, d, w):
    """Unlabelled training pairs with p_yes, pseudo, passes' u; the truth joined for measuring alone."""
    ev, lab, un, pre = setting(spark, d, w)
    model = K.tuned(pre, lab)
    scored = S.uncertainty(model.passes(model.score(un)))
    return cut(scored.select("pair_id", "ev", "p_yes", F.col("pred").alias("pseudo"), "u", "u_micro")), ev.select("pair_id", "y")


def confidences(spark, d, w):
    """Unlabelled training pairs with p_yes and pseudo: no dropout passes."""
    _, lab, un, pre = setting(spark, d, w)
    return cut(K.tuned(pre, lab).score(un).select("pair_id", "p_yes", F.col("pred").alias("pseudo")))


def random_selected(spark, d, w, share):
    """pair_id, pseudo of a random share of the unlabelled pairs.

    Labels and the draw are decided by hashes of pair_id, so that evidence is made for
    the labelled and the drawn pairs alone.
    """
    left, right = W.sequences(spark, d, w)
    p = cut(W.pairs(spark, d, w))
    lab, un = S.take_labels(p.where("split = 'train'"), p.count(), W.DEFAULT_RATE[w])
    drawn = S.select_random(un, share)[0]
    both = lab.select("pair_id", "left_id", "right_id", "y").unionByName(drawn.select("pair_id", "left_id", "right_id", F.lit(None).cast("int").alias("y")))
    ev = cut(K.evidence_of(both, left, right).select("pair_id", "y", "ev"))
    return K.tuned(K.pretext_counts(spark, d), ev.where("y is not null")).score(ev.where("y is null")).select("pair_id", F.col("pred").alias("pseudo"))


def _sequences(w, i):
    def run(spark, d):
        return W.sequences(spark, d, w)[i].select("id", "seq")

    return run


def _prompt(shape):
    def run(spark, d):
        left, right = W.sequences(spark, d, "w1")
        p = W.attach(W.pairs(spark, d, "w1"), left, right)
        t = Template(shape, "hard")
        return p.select("pair_id", t.apply(F.col("left_seq"), F.col("right_seq")).alias("prompt"), t.slot_position(F.col("left_seq"), F.col("right_seq")).alias("slot"))

    return run


def _prompt_sql(shape):
    body = {"t1": "concat_ws(' ', left_seq, right_seq, 'They', 'are', '[MASK]')", "t2": "concat_ws(' ', left_seq, 'is', '[MASK]', 'to', right_seq)"}[shape]
    n = lambda c: f"len(string_split({c}, ' '))"
    slot = {"t1": f"{n('left_seq')} + {n('right_seq')} + 2", "t2": f"{n('left_seq')} + 1"}[shape]
    return f"with {O.pairs_cte('w1')} select pair_id, {body} as prompt, ({slot})::int as slot from pairs"


SOFT = tuple((s, k) for s in ("t1", "t2") for k in (1, 3))


def prompt_soft_layout(spark, d):
    """Learned templates laid out over w1's pairs: the prompt with its learned places, and where the slot is."""
    left, right = W.sequences(spark, d, "w1")
    p = W.attach(W.pairs(spark, d, "w1"), left, right)
    a, b, out = F.col("left_seq"), F.col("right_seq"), None
    for s, k in SOFT:
        t = Template(s, "soft", k)
        one = p.select("pair_id", F.lit(s).alias("shape"), F.lit(k).alias("k"), t.apply(a, b).alias("prompt"), t.slot_position(a, b).alias("slot"))
        out = one if out is None else out.unionByName(one)
    return out


def _soft_sql(s, k):
    marks = lambda i: ", ".join(f"'[P{i * k + j}]'" for j in range(k))
    n = lambda c: f"len(string_split({c}, ' '))"
    body = {"t1": f"left_seq, right_seq, {marks(0)}, {marks(1)}, '[MASK]'", "t2": f"left_seq, {marks(0)}, '[MASK]', {marks(1)}, right_seq"}[s]
    slot = {"t1": f"{n('left_seq')} + {n('right_seq')} + {2 * k}", "t2": f"{n('left_seq')} + {k}"}[s]
    return f"select pair_id, '{s}' as shape, {k}::int as k, concat_ws(' ', {body}) as prompt, ({slot})::int as slot from pairs"


SOFT_SQL = f"with {O.pairs_cte('w1')} " + " union all ".join(_soft_sql(s, k) for s, k in SOFT)


def ser_pair(spark, d):
    left, right = W.sequences(spark, d, "w4")
    p = W.attach(W.pairs(spark, d, "w4"), left, right)
    return p.select("pair_id", encode_pair(F.col("left_seq"), F.col("right_seq")).alias("input"))


def ser_truncated(spark, d):
    left, right = W.sequences(spark, d, "w7")
    p = W.attach(W.pairs(spark, d, "w7"), left, right)
    a, b = truncate_pair(F.col("left_seq"), F.col("right_seq"), 64)
    return p.select("pair_id", a.alias("left_part"), b.alias("right_part"))


TRUNCATED_SQL = f"""with {O.pairs_cte('w7')}, s as (select pair_id, string_split(left_seq, ' ') as a, string_split(right_seq, ' ') as b from pairs),
k as (select *, least(len(a), greatest(32, 64 - len(b))) as ka from s)
select pair_id, array_to_string(a[1:ka], ' ') as left_part, array_to_string(b[1:least(len(b), 64 - ka)], ' ') as right_part from k"""


def workload_stats(spark, d):
    out = None
    for w in KEYED:
        p = W.pairs(spark, d, w).agg(F.count("*").alias("pairs"), F.sum("y").cast("long").alias("positives"), F.countDistinct("left_id").alias("left_rows"), F.countDistinct("right_id").alias("right_rows"))
        p = p.select(F.lit(w).alias("workload"), "pairs", "positives", "left_rows", "right_rows", F.floor(F.col("pairs") * W.DEFAULT_RATE[w] + 0.5).cast("long").alias("train_labels"))
        out = p if out is None else out.unionByName(p)
    return out


WORKLOAD_STATS_SQL = " union all ".join(
    f"(with {O.pairs_cte(w)} select '{w}' as workload, count(*) as pairs, sum(y)::bigint as positives, count(distinct left_id) as left_rows, count(distinct right_id) as right_rows, floor(count(*) * {W.DEFAULT_RATE[w]} + 0.5)::bigint as train_labels from pairs)" for w in KEYED
)


def split_counts(spark, d):
    return W.pairs(spark, d, "w1").groupBy("split").agg(F.count("*").alias("n"), F.sum("y").cast("long").alias("positives"))


def label_rate_nested(spark, d):
    """How many labelled pairs each rate shares with the next."""
    ev = cut(W.pairs(spark, d, "w1"))
    train, n = ev.where("split = 'train'"), ev.count()
    out, last = None, None
    for r in (0.05, 0.10, 0.15, 0.20, 0.25):
        lab = S.take_labels(train, n, r)[0].select("pair_id")
        inside = last.join(lab, "pair_id", "left_semi").count() if last is not None else 0
        row = lab.agg(F.count("*").alias("n")).select(F.lit(r).alias("rate"), "n", F.lit(inside).cast("long").alias("held_from_last"))
        out, last = (row if out is None else out.unionByName(row)), lab
    return out


def _lab_sql(r):
    return O.labelled_cte(r, f"lab{round(r * 100)}")


LABEL_RATE_SQL = f"with {O.pairs_cte('w1')}, " + ", ".join(_lab_sql(r) for r in (0.05, 0.10, 0.15, 0.20, 0.25)) + " " + " union all ".join(
    f"select {r}::double as rate, (select count(*) from lab{round(r * 100)}) as n, (select count(*) from lab{round(r * 100)} where pair_id in (select pair_id from lab{round(p * 100)}))::bigint as held_from_last" if p else f"select {r}::double as rate, (select count(*) from lab{round(r * 100)}) as n, 0::bigint as held_from_last" for r, p in ((0.05, 0), (0.10, 0.05), (0.15, 0.10), (0.20, 0.15), (0.25, 0.20))
)


def label_count_80(spark, d):
    p = cut(W.pairs(spark, d, "w1"))
    return S.take_labels(p.where("split = 'train'"), p.count(), count=80)[0].select("pair_id", "y")


LABEL_80_SQL = f"with {O.pairs_cte('w1')} select pair_id, y from ({O.lowest(O.duck_sql('H(' + chr(39) + 'lab|' + chr(39) + ' || pair_id)'), '(select * from pairs where split = ' + chr(39) + 'train' + chr(39) + ')', '80')})"


def count_pretext(spark, d):
    return K.pretext_counts(spark, d).select("word", "f", F.col("n").cast("long").alias("n"))


def word_probabilities(spark, d):
    ev, lab, _, pre = setting(spark, d, "w1")
    e = K.tuned(pre, lab).with_words(ev)
    total = sum((F.col("word_e")[i] for i in range(1, len(K.WORDS))), F.col("word_e")[0])
    return e.select("pair_id", *[F.round(F.col("word_e")[i] / total, 6).alias(f"p_{w}") for i, w in enumerate(K.WORDS)])


WORD_P_SQL = f"with {O.base('w1', 0.10)}, {O.score_cte()} select pair_id, " + ", ".join(f"round(sum(case when word = {i} then q end) / sum(q), 6) as p_{w}" for i, w in enumerate(K.WORDS)) + " from scorede group by pair_id"


def class_scores_simple(spark, d):
    ev, lab, _, pre = setting(spark, d, "w1")
    return K.tuned(pre, lab, Verbalizer.simple()).score(ev).select("pair_id", "p_yes", "pred")


SIMPLE_SQL = f"with {O.pairs_cte('w1')}, {O.evidence_cte()}, {O.pretext_cte()}, {O.labelled_cte(0.10)}, {O.model_cte('lab', yes=(0,), no=(3,))}, {O.score_cte(yes=(0,), no=(3,))} select pair_id, p_yes, (p_yes > 0.5)::int as pred from scored"


def mc_uncertainty(spark, d):
    s, _ = unlabelled_scored(spark, d, "w1")
    return s.select("pair_id", "p_yes", "pseudo", "u")


def _selector(kind):
    def run(spark, d):
        if kind == "random":
            return random_selected(spark, d, "w1", 0.10)
        s = confidences(spark, d, "w1") if kind == "confidence" else unlabelled_scored(spark, d, "w1")[0]
        return S.SELECTORS[kind](s, 0.10)[0].select("pair_id", "pseudo")

    return run


def _selected_sql(kind):
    n = "floor((select count(*) from uns) * 0.1 + 1e-9)"
    if kind == "balanced":
        parts = [f"select pair_id, pseudo from ({O.lowest('u_micro', f'(select * from uns where pseudo = {c})', f'floor((select count(*) from uns where pseudo = {c}) * 0.1 + 1e-9)')})" for c in (0, 1)]
        return " union all ".join(parts)
    score = {"uncertainty": "u_micro", "confidence": "-round(greatest(p_yes, 1 - p_yes) * 1000000)::bigint", "random": O.duck_sql("H('rand|' || pair_id)")}[kind]
    return f"select pair_id, pseudo from ({O.lowest(score, 'uns', n)})"


SELECTED = ("uncertainty", "confidence", "random", "balanced")


def selector_quality(spark, d):
    s, truth = unlabelled_scored(spark, d, "w1")
    out = None
    for kind in SELECTED:
        chosen = S.SELECTORS[kind](s, 0.10)[0].join(truth, "pair_id")
        row = Q.tpr_tnr(chosen).select(F.lit(kind).alias("selector"), "selected", "tpr", "tnr")
        out = row if out is None else out.unionByName(row)
    return out


SELECTOR_SQL = f"with {O.unlabelled_scores('w1', 0.10)}, " + ", ".join(f"s_{k} as ({_selected_sql(k)})" for k in SELECTED) + " " + " union all ".join(
    f"select '{k}' as selector, count(*) as selected, round(count(*) filter (u.y = 1 and s.pseudo = 1)::double / nullif(count(*) filter (u.y = 1), 0), 6) as tpr, round(count(*) filter (u.y = 0 and s.pseudo = 0)::double / nullif(count(*) filter (u.y = 0), 0), 6) as tnr from s_{k} s join uns u on u.pair_id = s.pair_id" for k in SELECTED
)


def _norms(spark, d):
    ev, lab, _, pre = setting(spark, d, "w1")
    model = K.tuned(pre, lab)
    return model, cut(S.mc_el2n(model.passes(model.score(lab))).select("pair_id", "ev", "y", "p_yes", "e", "e_micro"))


def el2n_rows(spark, d):
    return S.el2n(_norms(spark, d)[1].drop("e", "e_micro")).select("pair_id", "y", "e")


def mc_el2n_rows(spark, d):
    return _norms(spark, d)[1].select("pair_id", "y", "e")


def prune_once(spark, d):
    return S.prune(_norms(spark, d)[1], 0.3)[0].select("pair_id", "y")


NORMS = f"{O.base('w1', 0.10)}, {O.score_cte()}, {O.score_cte('m', 'pas', O.KEEP, 'pass')}, nrm as (select l.pair_id, l.y, round(sqrt(2.0::double) * (sum(abs(l.y - pas.p_yes)) / 10), 6) as e, round(round(sqrt(2.0::double) * (sum(abs(l.y - pas.p_yes)) / 10), 6) * 1000000)::bigint as e_micro from lab l join pas on pas.pair_id = l.pair_id group by l.pair_id, l.y)"


def prune_schedule(spark, d):
    """Rows left after each of three prunes, for each rate, from the labelled set's size."""
    n0 = S.take_labels((p := cut(W.pairs(spark, d, "w1"))).where("split = 'train'"), p.count(), 0.10)[0].count()
    rows = []
    for r in (0.1, 0.2, 0.3, 0.4, 0.5):
        n = n0
        for k in (1, 2, 3):
            n -= S.share(n, r)
            rows.append((r, k, n, Q.example_epochs(n0, r)))
    return spark.createDataFrame(rows, "e_r double, prune int, n_left long, example_epochs long")


def prf_by_workload(spark, d):
    out = None
    for w in KEYED:
        one = Q.prf(predicted(spark, d, w).where("split = 'test'")).select(F.lit(w).alias("workload"), "tp", "fp", "fn", "precision", "recall", "f1")
        out = one if out is None else out.unionByName(one)
    return out


PRF_SQL = " union all ".join(
    f"(with {O.base(w, W.DEFAULT_RATE[w])}, {O.score_cte()}, t as (select y, (p_yes > 0.5)::int as pred from scored where split = 'test') select '{w}' as workload, * from ({O.PRF.format('t')}))" for w in KEYED
)


def pr_curve(spark, d):
    return Q.pr_curve(predicted(spark, d, "w1").where("split = 'test'")).select("p_yes", F.col("tp").cast("long"), F.col("predicted").cast("long"))


def self_trained(spark, d, w, cfg=None):
    ev, lab, un, pre = setting(spark, d, w)
    return (*S.self_train(S.CountTeacher(pre), lab, un, ev.where("split = 'valid'"), cfg), ev)


def self_train_w1(spark, d):
    model, log, _, ev = self_trained(spark, d, "w1")
    return Q.prf(model.score(ev.where("split = 'test'")))


def student_f1_w1(spark, d):
    """One iteration without pruning: the student's P/R/F1 on the test split."""
    model, _, _, ev = self_trained(spark, d, "w1", S.SelfTrainConfig(pruning=False))
    return Q.prf(model.score(ev.where("split = 'test'")))


STUDENT_SQL = f"with {O.unlabelled_scores('w1', 0.10)}, sel as ({_selected_sql('uncertainty')}), lab2 as (select pair_id, y from lab union all select pair_id, pseudo as y from sel), {O.model_cte('lab2', 'n')}, {O.score_cte('n', 'fin')}, t as (select y, (p_yes > 0.5)::int as pred from fin where split = 'test') {O.PRF.format('t')}"


def ablation_grid(spark, d):
    """E5 on the counting backbone: full, without self-training, without pruning, ordinary self-training."""
    ev, lab, un, pre = setting(spark, d, "w1")
    rows = []
    for name, cfg in (("full", S.SelfTrainConfig()), ("no_self_training", S.SelfTrainConfig(iters=0)), ("no_pruning", S.SelfTrainConfig(pruning=False)), ("confidence_all", S.SelfTrainConfig(selector="all", pruning=False))):
        model, log, last = S.self_train(S.CountTeacher(pre), lab, un, ev.where("split = 'valid'"), cfg)
        r = Q.prf(model.score(ev.where("split = 'test'"))).first()
        rows.append((name, r["precision"], r["recall"], r["f1"], last.count()))
    return spark.createDataFrame(rows, "variant string, precision double, recall double, f1 double, train_rows long")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Serialise, cloze-score, pick pseudo-labels by uncertainty, prune, and measure, on w1."""
    return self_train_w1(spark, sf_dir)


def library_queries() -> dict:
    q = {f"pairs_{w}": (lambda s, d, w=w: pair_rows(s, d, w)) for w in KEYED}
    q |= {f"ser_{w}_{n}": _sequences(w, i) for w in KEYED for i, n in enumerate(("left", "right"))}
    q |= {f"predict_{w}": (lambda s, d, w=w: predicted(s, d, w)) for w in KEYED}
    q |= {"prompt_t1_hard": _prompt("t1"), "prompt_t2_hard": _prompt("t2"), "prompt_soft_layout": prompt_soft_layout, "ser_pair_input": ser_pair, "ser_truncate_longest_first": ser_truncated}
    q |= {f"select_{k}_w1": _selector(k) for k in SELECTED}
    q |= {"workload_stats": workload_stats, "split_counts": split_counts, "label_rate_nested": label_rate_nested, "label_count_80": label_count_80, "count_pretext_table": count_pretext}
    q |= {"word_probabilities": word_probabilities, "class_scores_simple_words": class_scores_simple, "mc_uncertainty_w1": mc_uncertainty, "selector_tpr_tnr": selector_quality, "el2n_w1": el2n_rows, "mc_el2n_w1": mc_el2n_rows}
    q |= {"prune_once_w1": prune_once, "prune_schedule_w1": prune_schedule, "prf_by_workload": prf_by_workload, "pr_curve_w1": pr_curve, "self_train_w1": self_train_w1, "student_without_pruning_w1": student_f1_w1, "ablation_grid": ablation_grid}
    from pairmatch import more_queries, record_queries

    return q | more_queries.queries() | record_queries.queries()


def library_oracles() -> dict[str, str]:
    o = {f"pairs_{w}": f"with {O.pairs_cte(w)} select pair_id, y, split from pairs" for w in KEYED}
    o |= {f"ser_{w}_{n}": f"select id, seq from ({O.side(w, i)})" for w in KEYED for i, n in enumerate(("left", "right"))}
    o |= {f"predict_{w}": f"with {O.base(w, W.DEFAULT_RATE[w])}, {O.score_cte()} select pair_id, y, split, p_yes, (p_yes > 0.5)::int as pred from scored" for w in KEYED}
    o |= {"prompt_soft_layout": SOFT_SQL, "prompt_t1_hard": _prompt_sql("t1"), "prompt_t2_hard": _prompt_sql("t2"), "ser_truncate_longest_first": TRUNCATED_SQL}
    o |= {"ser_pair_input": f"with {O.pairs_cte('w4')} select pair_id, concat_ws(' ', '[CLS]', left_seq, '[SEP]', right_seq, '[SEP]') as input from pairs"}
    o |= {f"select_{k}_w1": f"with {O.unlabelled_scores('w1', 0.10)} {_selected_sql(k)}" for k in SELECTED}
    o |= {"workload_stats": WORKLOAD_STATS_SQL, "split_counts": f"with {O.pairs_cte('w1')} select split, count(*) as n, sum(y)::bigint as positives from pairs group by split", "label_rate_nested": LABEL_RATE_SQL, "label_count_80": LABEL_80_SQL}
    o |= {"count_pretext_table": f"with {O.pretext_cte()} select word, f, n from pre", "word_probabilities": WORD_P_SQL, "class_scores_simple_words": SIMPLE_SQL}
    o |= {"mc_uncertainty_w1": f"with {O.unlabelled_scores('w1', 0.10)} select pair_id, p_yes, pseudo, u from uns", "selector_tpr_tnr": SELECTOR_SQL}
    o |= {"el2n_w1": f"with {O.base('w1', 0.10)}, {O.score_cte()} select l.pair_id, l.y, round(sqrt(2.0::double) * abs(l.y - s.p_yes), 6) as e from lab l join scored s on s.pair_id = l.pair_id", "mc_el2n_w1": f"with {NORMS} select pair_id, y, e from nrm"}
    o |= {"prune_once_w1": f"with {NORMS} select pair_id, y from nrm where pair_id not in (select pair_id from ({O.lowest('e_micro', 'nrm', 'floor((select count(*) from nrm) * 0.3 + 1e-9)')}))"}
    o |= {"prf_by_workload": PRF_SQL, "student_without_pruning_w1": STUDENT_SQL}
    o |= {"pr_curve_w1": f"with {O.base('w1', 0.10)}, {O.score_cte()}, g as (select p_yes, sum(y) as pos, count(*) as n from scored where split = 'test' group by p_yes) select p_yes, (sum(pos) over (order by p_yes desc))::bigint as tp, (sum(n) over (order by p_yes desc))::bigint as predicted from g"}
    from pairmatch import more_queries, record_queries

    return o | more_queries.oracles() | record_queries.oracles()
