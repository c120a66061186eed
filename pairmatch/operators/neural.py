"""Neural matchers on Spark: one task trains one configuration, all tasks score.

Labels are few, so a training run is the parallel unit: a table of runs meets the
labelled rows, and each group becomes a model in one task. Parameters come back as
rows, are bounded by the configuration and not by data, and go out with the scoring
function. Full-data training averages gradients of partitions step by step.
"""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession, functions as F

from pairmatch.functions import neural as N
from pairmatch.functions.templates import Template, Verbalizer

METHODS = ("proposed", "no_prompt", "no_self_training", "no_pruning", "attr_rnn", "pair_lm", "siamese", "augmented_lm", "domain_adapt", "meta_aug", "jaccard", "constant_yes")


def make(kind: str, spec: dict | None = None, source_rows=None) -> N.Matcher:
    """cloze, head, siamese, attr_rnn, augmented, domain_adapt or meta_aug by name; spec overrides the defaults."""
    s = dict(spec or {})
    cfg = N.NetConfig(**s.get("net", {}))
    if kind == "cloze":
        verb = Verbalizer.simple() if s.get("words") == "simple" else Verbalizer.general()
        return N.ClozeMatcher(Template(s.get("shape", "t2"), s.get("template", "soft")), verb, cfg)
    if kind == "domain_adapt":
        return N.DomainAdaptMatcher(source_rows or [], cfg, s.get("align", "moments"))
    if kind in ("augmented", "meta_aug"):
        cls = {"augmented": N.AugmentedMatcher, "meta_aug": N.MetaAugMatcher}[kind]
        return cls(cfg, s.get("idf"), s.get("tags", True), s.get("summary", True), s.get("augmented", True))
    return {"head": N.HeadMatcher, "siamese": N.SiameseMatcher, "attr_rnn": N.AttrRnnMatcher}[kind](cfg)


def fit_runs(train: DataFrame, runs: list[dict]) -> DataFrame:
    """run_id, name, shape, data of each run's tensors. runs: [{"run_id", "kind", "spec"}]; train: pair_id, left_seq, right_seq, y, role."""
    spark = train.sparkSession
    table = spark.createDataFrame([(r["run_id"], json.dumps(r)) for r in runs], "run_id string, run string")

    def train_one(pdf):
        import pandas as pd

        run = json.loads(pdf["run"].iloc[0])
        rows = pdf.sort_values("pair_id").to_dict("records")
        by = lambda role: [r for r in rows if r["role"] == role]
        m = make(run["kind"], run.get("spec"), by("source")).fit(by("label"), by("valid"), run.get("epochs"))
        return pd.DataFrame([(run["run_id"], *b) for b in m.bundle()], columns=["run_id", "name", "shape", "data"])

    both = train.select("pair_id", "left_seq", "right_seq", "y", "role").crossJoin(F.broadcast(table))  # as many copies as runs
    return both.groupBy("run_id").applyInPandas(train_one, "run_id string, name string, shape array<int>, data array<double>")


class NeuralModel:
    """A trained matcher: scores pairs, with or without dropout, in Arrow batches."""

    def __init__(self, kind: str, spec: dict | None, tensors: list[tuple]):
        self.kind, self.spec, self.tensors = kind, spec, tensors

    def _add(self, df: DataFrame, column: str, dtype: str, value) -> DataFrame:
        kind, spec, tensors = self.kind, self.spec, self.tensors

        def run(batches):
            model = make(kind, spec).load(tensors)
            for pdf in batches:
                yield pdf.assign(**{column: value(model, pdf.to_dict("records"))})

        schema = df.schema.simpleString()[len("struct<") : -1]
        return df.mapInPandas(run, ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields], f"{column} {dtype}"])) if schema else df

    def score(self, df: DataFrame) -> DataFrame:
        out = self._add(df, "p_yes", "double", lambda m, rows: m.predict(rows).round(6))
        return out.withColumn("pred", (F.col("p_yes") > 0.5).cast("int")).withColumn("conf", F.greatest("p_yes", 1 - F.col("p_yes")))

    def passes(self, df: DataFrame, n: int = 10) -> DataFrame:
        return self._add(df, "p_passes", "array<double>", lambda m, rows: [x.tolist() for x in m.predict_passes(rows, n).round(6)])

    def vectors(self, df: DataFrame) -> DataFrame:
        """Adds vec: the pair's vector, dropout off."""
        return self._add(df, "vec", "array<double>", lambda m, rows: [x.tolist() for x in m.vectors(rows).round(6)])

    def save(self, spark: SparkSession, path: str) -> None:
        spark.createDataFrame([(self.kind, json.dumps(self.spec or {}), *t) for t in self.tensors], "kind string, spec string, name string, shape array<int>, data array<double>").write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> NeuralModel:
        rows = spark.read.parquet(path).collect()  # as many rows as the net has tensors
        return NeuralModel(rows[0]["kind"], json.loads(rows[0]["spec"]), [(r["name"], r["shape"], r["data"]) for r in rows])


class NeuralLearner:
    """fit(train) for the self-training loop; train has pair_id, left_seq, right_seq, y."""

    columns = ("left_seq", "right_seq")

    def __init__(self, kind: str = "cloze", spec: dict | None = None, epochs: int = 8):
        self.kind, self.spec, self.epochs = kind, spec, epochs

    def fit(self, train: DataFrame) -> NeuralModel:
        runs = [{"run_id": "0", "kind": self.kind, "spec": self.spec, "epochs": self.epochs}]
        rows = fit_runs(train.withColumn("role", F.lit("label")), runs).collect()  # tensors of one net
        return NeuralModel(self.kind, self.spec, [(r["name"], r["shape"], r["data"]) for r in rows])


def _added(pdf):
    import numpy as np
    import pandas as pd

    return pd.DataFrame([(pdf["name"].iloc[0], int(pdf["chunk"].iloc[0]), np.sum(np.stack(pdf["g"].to_numpy()), 0).tolist())], columns=["name", "chunk", "g"])


def fit_allreduce(train: DataFrame, kind: str = "cloze", spec: dict | None = None, steps: int = 5) -> NeuralModel:
    """Full-batch steps over any number of rows: partitions sum gradients, the driver updates.

    Gradients go as chunks of arrays and are added in two levels, so that no task holds
    those of all partitions; the driver gets one.
    """
    from pairmatch.functions import tape as T

    model = make(kind, spec).build()
    opt = T.AdamW(model.net.params, model.cfg.lr)
    n = train.count()
    for step in range(steps):
        tensors = model.bundle()

        def gradients(batches, tensors=tensors, step=step):
            import numpy as np
            import pandas as pd

            local = make(kind, spec).load(tensors)
            total: dict = {}
            for pdf in batches:
                rows = pdf.to_dict("records")
                for i in range(0, len(rows), 64):
                    part = rows[i : i + 64]
                    (local.loss(part, [r["pair_id"] for r in part], step) * float(len(part))).backward()
                    for k, v in local.net.params.items():
                        if v.grad is not None:
                            total[k] = total.get(k, 0) + v.grad
                            v.grad = None
            yield pd.DataFrame([(k, i // 4096, np.ravel(g)[i : i + 4096].tolist()) for k, g in total.items() for i in range(0, g.size, 4096)], columns=["name", "chunk", "g"])

        parts = train.select("pair_id", "left_seq", "right_seq", "y").mapInPandas(gradients, "name string, chunk int, g array<double>")
        some = parts.withColumn("b", F.spark_partition_id() % 64).groupBy("name", "chunk", "b").applyInPandas(_added, "name string, chunk int, g array<double>")
        rows = some.groupBy("name", "chunk").applyInPandas(_added, "name string, chunk int, g array<double>").collect()  # one net's gradient
        for k, v in model.net.params.items():
            got = sorted((r["chunk"], r["g"]) for r in rows if r["name"] == k)
            if got:
                import numpy as np

                v.grad = np.concatenate([np.array(g) for _, g in got]).reshape(v.v.shape) / n
        opt.step()
    return NeuralModel(kind, spec, model.bundle())


def jaccard_rows(rows):
    import re

    def one(r):
        a, b = (set(re.findall(r"[^\W_]+", r[c].lower())) - {"col", "val"} for c in ("left_seq", "right_seq"))
        return len(a & b) / max(1, len(a | b))

    return [one(r) for r in rows]


SELF = ("proposed", "no_prompt", "no_self_training", "no_pruning")
OF_TEACHER = ("net", "shape", "template", "words", "epochs", "passes")  # what of a run's settings its teacher depends on


def kind_of(method: str) -> str:
    return "head" if method == "no_prompt" else "cloze"


def teacher_of(method: str, rows: dict[str, list[dict]], spec: dict) -> N.Matcher:
    return make(kind_of(method), spec).fit(rows["label"], rows["valid"], spec.get("epochs", 20))


def teacher_scores(model: N.Matcher, un: list[dict], n: int, vectors: bool = False) -> dict:
    """p, u: P(yes) and the passes' spread of each unlabelled row; vec: its vector, if asked for."""
    import numpy as np

    un = model.ready(un)
    return {"p": model.predict(un), "u": model.predict_passes(un, n).std(1).round(6), "vec": model.vectors(un) if vectors else np.zeros((len(un), 0))}


def run_method(method: str, rows: dict[str, list[dict]], spec: dict, teacher=None, scores=None) -> dict:
    """One experiment in one task, by default with the reported 20 teacher and 30 student epochs, pruning every 8 (of other counts in proportion, so that no run goes without). rows: label, unlabel (y hidden from the models), valid, test, source. teacher: a trained teacher's tensors, scores: teacher_scores of unlabel, where they are at hand."""
    import hashlib
    import time

    import numpy as np

    lab, un, valid, test = (rows[k] for k in ("label", "unlabel", "valid", "test"))
    truth = {r["pair_id"]: r["y"] for r in un}
    un = [{k: v for k, v in r.items() if k != "y"} for r in un]
    epochs, u_r, e_r, n = spec.get("epochs", 20), spec.get("u_r", 0.1), spec.get("e_r", 0.2), spec.get("passes", 10)
    student = int(epochs * 1.5)
    every = spec.get("every") or max(1, round(student * 8 / 30))
    began, extra = time.time(), {}
    if method == "constant_yes":
        p = np.ones(len(test))
    elif method == "jaccard":
        s, y = np.array(jaccard_rows(valid + lab)), [r["y"] for r in valid + lab]
        cut = max(np.unique(s), key=lambda c: N.f1(y, s >= c), default=0.5)
        p = (np.array(jaccard_rows(test)) >= cut).astype(float)
    elif method in SELF:
        kind = kind_of(method)
        model = make(kind, spec).load(teacher) if teacher else teacher_of(method, rows, spec)
        if method != "no_self_training":
            how = spec.get("selector", "uncertainty")
            scores = scores or teacher_scores(model, un, n, how == "clustering")
            p_un, u = scores["p"], scores["u"]
            tie = [hashlib.md5(("tie|" + r["pair_id"]).encode()).hexdigest() for r in un]
            score = {"uncertainty": u, "confidence": -np.maximum(p_un, 1 - p_un).round(6), "random": np.array([int(t[8:16], 16) for t in tie], float)}.get(how)
            label = (p_un > 0.5).astype(int)
            if how == "clustering":
                score, label = cluster_scores(scores["vec"], label)
            order = sorted(range(len(un)), key=lambda i: (score[i], tie[i]))[: int(len(un) * u_r + 1e-9)]
            chosen = [un[i] | {"y": int(label[i])} for i in order]
            pos = [i for i in order if truth[un[i]["pair_id"]] == 1]
            neg = [i for i in order if truth[un[i]["pair_id"]] == 0]
            extra = {"tpr": float(np.mean([label[i] == 1 for i in pos])) if pos else None, "tnr": float(np.mean([label[i] == 0 for i in neg])) if neg else None}
            model = make(kind, spec).fit(lab + chosen, valid, student, None if method == "no_pruning" else (every, e_r, n))
            extra["example_epochs"] = float(sum(x["rows"] for x in model.log))
        p = model.predict(test)
    else:
        kind = {"pair_lm": "head", "augmented_lm": "augmented"}.get(method, method)
        if kind in ("augmented", "meta_aug"):  # weights of the workload's own words; labels play no part
            spec = spec | {"idf": N.term_weights([r[c] for r in lab + un + valid + test for c in ("left_seq", "right_seq")])}
        model = make(kind, spec, rows.get("source") or lab).fit(lab, valid, epochs)
        p = model.predict(test)
    y, yes = np.array([r["y"] for r in test], bool), p > 0.5
    tp, fp, fn = int((y & yes).sum()), int((~y & yes).sum()), int((y & ~yes).sum())
    return {"tp": tp, "fp": fp, "fn": fn, "precision": 100 * tp / max(1, tp + fp), "recall": 100 * tp / max(1, tp + fn), "f1": 200 * tp / max(1, 2 * tp + fp + fn), "seconds": time.time() - began} | extra


def cluster_scores(x, label, k: int = 2):
    """Distance to the own centre of a small k-means, and the cluster's majority label."""
    import numpy as np

    at = np.argsort(x[:, 0])
    centre = x[at[np.linspace(0, len(x) - 1, k).astype(int)]]
    for _ in range(20):
        own = ((x[:, None] - centre[None]) ** 2).sum(2).argmin(1)
        centre = np.stack([x[own == c].mean(0) if (own == c).any() else centre[c] for c in range(k)])
    major = np.array([int(label[own == c].mean() > 0.5) if (own == c).any() else 0 for c in range(k)])
    return np.sqrt(((x - centre[own]) ** 2).sum(1)).round(6), major[own]


RESULT = "run_id string, workload string, method string, setting string, precision double, recall double, f1 double, tpr double, tnr double, seconds double, example_epochs double, peak_mb double"


COLUMNS = ("pair_id", "left_seq", "right_seq", "y", "role")


def _pack(table) -> bytes:
    """Rows of a workload as one value: a text that many pairs have is in it once."""
    import pyarrow as pa

    table = table.select(COLUMNS)
    for c in ("left_seq", "right_seq", "role"):
        table = table.set_column(COLUMNS.index(c), c, table.column(c).combine_chunks().dictionary_encode())
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(table.combine_chunks())
    return sink.getvalue().to_pybytes()


def _unpack(data: bytes) -> list[dict]:
    """The rows by pair_id; pairs of one record share its text."""
    import pyarrow as pa

    table, cells = pa.ipc.open_stream(data).read_all(), []
    for c in COLUMNS:
        got = []
        for chunk in table.column(c).chunks:
            if pa.types.is_dictionary(chunk.type):
                words = chunk.dictionary.to_pylist()
                got += [None if i is None else words[i] for i in chunk.indices.to_pylist()]
            else:
                got += chunk.to_pylist()
        cells.append(got)
    return sorted((dict(zip(COLUMNS, r, strict=True)) for r in zip(*cells, strict=True)), key=lambda r: r["pair_id"])


def run_experiments(rows: DataFrame, runs: list[dict]) -> DataFrame:
    """rows: workload, pair_id, left_seq, right_seq, y, role; runs: [{run_id, workload, method, setting, spec}], rows besides if its rows have another name than its workload. One task a run.

    A workload is put together once, with each text once, and every run is sent that
    value; runs are dealt by their number, so that no two are in one task while others wait.
    Runs whose teachers learn the same are given one teacher, and its scores of the
    unlabelled rows, which many tasks make. A run's seconds are those of its teacher, of
    all its scoring and its own.
    """
    from pairmatch.plans.session import cut

    spark, teachers, of = rows.sparkSession, {}, []
    for r in runs:
        at, spec = r.get("rows", r["workload"]), r.get("spec") or {}
        key = json.dumps([at, kind_of(r["method"]), {k: spec[k] for k in OF_TEACHER if k in spec}], sort_keys=True)
        of.append(teachers.setdefault(key, len(teachers)) if r["method"] in SELF else None)
    table = spark.createDataFrame([(i, r.get("rows", r["workload"]), json.dumps(r), t) for i, (r, t) in enumerate(zip(runs, of, strict=True))], "run_no int, workload string, run string, teacher int")

    def together(key, t):
        import pyarrow as pa

        return pa.table({"workload": [key[0].as_py()], "data": pa.array([_pack(t)], pa.binary())})

    def one(batches):
        import pyarrow as pa

        from pairmatch.operators.measures import peak_memory_mb

        for batch in batches:
            for run, data, fitted, scores, spent in zip(*(batch.column(c) for c in ("run", "data", "fitted", "scores", "spent")), strict=True):
                run, by = json.loads(run.as_py()), _by_role(data)
                got = run_method(run["method"], by, run.get("spec", {}), _loaded(fitted.as_py()), _loaded(scores.as_py()))
                got["seconds"] += spent.as_py() or 0.0
                vals = [got.get(k) for k in ("precision", "recall", "f1", "tpr", "tnr", "seconds", "example_epochs")]
                vals = [run["run_id"], run["workload"], run["method"], run["setting"], *[float("nan") if v is None else float(v) for v in vals], float(peak_memory_mb())]
                yield pa.record_batch([pa.array([v]) for v in vals], names=[x.split()[0] for x in RESULT.split(", ")])

    packs = cut(rows.select("workload", *COLUMNS).groupBy("workload").applyInArrow(together, "workload string, data binary"))
    met = packs.join(F.broadcast(table), "workload")  # the list of runs is the caller's
    if teachers:
        met = met.join(_taught(rows, packs, runs, of, teachers), "teacher", "left")
    else:
        met = met.withColumns({"fitted": F.lit(None).cast("binary"), "scores": F.lit(None).cast("binary"), "spent": F.lit(0.0)})
    return met.repartitionByRange(max(1, len(runs)), "run_no").select("run", "data", "fitted", "scores", "spent").mapInArrow(one, RESULT)


def _by_role(data) -> dict[str, list[dict]]:
    by: dict = {k: [] for k in ("label", "unlabel", "valid", "test", "source")}
    for r in _unpack(data.as_py()):
        by[r["role"]].append(r)
    return by


def _saved(arrays) -> bytes:
    """Arrays by name as one value."""
    import io

    import numpy as np

    out = io.BytesIO()
    np.savez(out, **arrays)
    return out.getvalue()


def _loaded(data: bytes | None):
    """Tensors as load() takes them, or scores by name."""
    import io

    import numpy as np

    if data is None:
        return None
    with np.load(io.BytesIO(data), allow_pickle=False) as found:
        arrays = {k: found[k] for k in found.files}
    return arrays if "p" in arrays and "u" in arrays else [(k, v.shape, v) for k, v in arrays.items()]


SCORED_ROWS = 1_000  # that one task scores


def _taught(rows: DataFrame, packs: DataFrame, runs: list[dict], of: list, teachers: dict[str, int]) -> DataFrame:
    """teacher, fitted, scores, spent: each teacher's tensors, its scores of the unlabelled rows by pair_id (null if none of its runs asks), and seconds."""
    from pairmatch.plans.session import cut

    spark = rows.sparkSession
    asks, vectors = ({t for r, t in zip(runs, of, strict=True) if t is not None and wanted(r)} for wanted in (lambda r: r["method"] != "no_self_training", lambda r: (r.get("spec") or {}).get("selector") == "clustering"))
    known = {t: json.loads(k) for k, t in teachers.items()}
    table = spark.createDataFrame([(t, at, json.dumps([kind, spec])) for t, (at, kind, spec) in known.items()], "teacher int, workload string, run string")

    def fit(batches):
        import time

        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for t, run, data in zip(*(batch.column(c) for c in ("teacher", "run", "data")), strict=True):
                (kind, spec), by, began = json.loads(run.as_py()), _by_role(data), time.time()
                model = teacher_of({"head": "no_prompt"}.get(kind, "proposed"), by, spec)
                fitted = _saved({k: np.array(x).reshape(shape) for k, shape, x in model.bundle()})
                yield pa.record_batch([pa.array([t.as_py()], pa.int32()), pa.array([fitted], pa.binary()), pa.array([time.time() - began])], names=["teacher", "fitted", "spent"])

    dealt = packs.join(F.broadcast(table), "workload").repartitionByRange(len(teachers), "teacher")  # the list is the caller's
    trained = cut(dealt.select("teacher", "run", "data").mapInArrow(fit, "teacher int, fitted binary, spent double"))
    if not asks:
        return trained.withColumn("scores", F.lit(None).cast("binary"))
    tensors = spark.sparkContext.broadcast({r["teacher"]: bytes(r["fitted"]) for r in trained.collect()})  # one net a teacher

    def score(batches):
        import time

        import pyarrow as pa

        models = {}
        for batch in batches:
            mine, un = batch.column("workload").to_pylist(), batch.select(["pair_id", "left_seq", "right_seq"]).to_pylist()
            for t in asks:
                at, kind, spec = known[t]
                part = [r for w, r in zip(mine, un, strict=True) if w == at]
                if not part:
                    continue
                if t not in models:
                    models[t] = make(kind, spec).load(_loaded(tensors.value[t]))
                began = time.time()
                got = teacher_scores(models[t], part, spec.get("passes", 10), t in vectors)
                cost = [time.time() - began] + [0.0] * (len(part) - 1)
                cells = [pa.array([t] * len(part), pa.int32()), pa.array([r["pair_id"] for r in part]), pa.array(got["p"]), pa.array(got["u"]), pa.array(got["vec"].tolist(), pa.list_(pa.float64())), pa.array(cost)]
                yield pa.record_batch(cells, names=["teacher", "pair_id", "p", "u", "vec", "cost"])

    def gather(key, t):
        import numpy as np
        import pyarrow as pa

        ids = t.column("pair_id").to_pylist()
        at = sorted(range(len(ids)), key=ids.__getitem__)
        vec = t.column("vec").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        data = _saved({"p": t.column("p").to_numpy()[at], "u": t.column("u").to_numpy()[at], "vec": vec[at]})
        return pa.table({"teacher": pa.array([key[0].as_py()], pa.int32()), "scores": pa.array([data], pa.binary()), "cost": [float(np.sum(t.column("cost").to_numpy()))]})

    un = rows.where("role = 'unlabel'").select("workload", "pair_id", "left_seq", "right_seq")
    un = un.repartition(max(1, -(-un.count() // SCORED_ROWS)))
    scored = un.mapInArrow(score, "teacher int, pair_id string, p double, u double, vec array<double>, cost double")
    made = cut(scored.groupBy("teacher").applyInArrow(gather, "teacher int, scores binary, cost double"))
    return trained.join(made, "teacher", "left").select("teacher", "fitted", "scores", (F.col("spent") + F.coalesce("cost", F.lit(0.0))).alias("spent"))


__all__ = ["METHODS", "NeuralLearner", "NeuralModel", "asdict", "fit_allreduce", "fit_runs", "make", "run_experiments", "run_method"]
