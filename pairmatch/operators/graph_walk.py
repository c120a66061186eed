"""The unsupervised baseline: a graph of records and their words, random walks, skip-gram vectors.

Nodes are records and tokens; a record's edges go to its tokens. A walk step is one
equi-join on (node, slot), where the slot is a hash of (walk, step) modulo the node's
degree, so walks are reproducible. Tokens over `max_degree` are left out: they are hubs
that tell nothing apart and would meet most of the walks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from pairmatch.plans.dialect import spark_sql


def edges(left: DataFrame, right: DataFrame, max_degree: int = 200) -> DataFrame:
    """src, dst, slot, degree; both directions. left, right: id, seq."""
    toks = lambda df, side: df.select(F.concat(F.lit(f"{side}:"), "id").alias("rec"), F.explode_outer(F.array_distinct(F.expr(spark_sql("KEEP(w, TOK(seq), w <> 'col' and w <> 'val')")))).alias("w"))
    both = toks(left, "L").unionByName(toks(right, "R")).where("w is not null").select("rec", F.concat(F.lit("w:"), "w").alias("tok"))
    near = both.groupBy("tok").agg(F.count("*").alias("n")).where(F.col("n").between(2, max_degree)).select("tok")
    both = both.join(near, "tok")
    way = both.select(F.col("rec").alias("src"), F.col("tok").alias("dst")).unionByName(both.select(F.col("tok").alias("src"), F.col("rec").alias("dst")))
    w = Window.partitionBy("src")
    return way.withColumn("slot", F.row_number().over(w.orderBy("dst")) - 1).withColumn("degree", F.count("*").over(w))


def walk_step(state: DataFrame, graph: DataFrame, step: int) -> DataFrame:
    """state: walk, node. Moves every walk one edge on."""
    degree = graph.select(F.col("src").alias("node"), "degree").distinct()
    h = F.expr(spark_sql(f"H('walk|' || walk || '|{step}')"))
    at = state.join(degree, "node").withColumn("slot", (h % F.col("degree")).cast("int"))
    return at.join(graph.select(F.col("src").alias("node"), "slot", "dst"), ["node", "slot"]).select("walk", F.col("dst").alias("node"))


def walks(graph: DataFrame, per_node: int = 4, length: int = 8) -> DataFrame:
    """walk, step, node of walks from every record."""
    from pairmatch.plans.session import cut

    graph = cut(graph)
    start = graph.where(~F.col("src").startswith("w:")).select("src").distinct()
    state = start.select("src", F.explode(F.sequence(F.lit(1), F.lit(per_node))).alias("k")).select(F.concat_ws("#", "src", "k").alias("walk"), F.col("src").alias("node"))
    out = state.withColumn("step", F.lit(0))
    for step in range(1, length):
        state = cut(walk_step(state, graph, step))
        out = out.unionByName(state.withColumn("step", F.lit(step)))
    return out.select("walk", "step", "node")


def vectors(found: DataFrame, dim: int = 32, seed: int = 7) -> DataFrame:
    """node, vec by skip-gram over the walks."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    lines = found.groupBy("walk").agg(F.array_sort(F.collect_list(F.struct("step", "node")))["node"].alias("path"))
    model = Word2Vec(vectorSize=dim, minCount=1, seed=seed, inputCol="path", outputCol="v", windowSize=4, maxIter=3).fit(lines)
    return model.getVectors().select(F.col("word").alias("node"), vector_to_array("vector").alias("vec"))


def cosine(a: str, b: str):
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a) * dot(b, b)))


def match(left: DataFrame, right: DataFrame, pairs: DataFrame, per_node: int = 4, length: int = 8, dim: int = 32, seed: int = 7) -> DataFrame:
    """pairs with sim and pred; no labels: a pair is a match if each is the other's best and the likeness is over the mean of such bests less a deviation."""
    from pairmatch.plans.session import cut

    v = cut(vectors(walks(edges(left, right), per_node, length), dim, seed))
    side = lambda s, i, c: v.where(F.col("node").startswith(f"{s}:")).select(F.expr("substring(node, 3)").alias(i), F.col("vec").alias(c))
    sim = pairs.join(side("L", "left_id", "u"), "left_id", "left").join(side("R", "right_id", "w"), "right_id", "left").withColumn("sim", F.coalesce(F.round(cosine("u", "w"), 6), F.lit(-1.0)))
    sim = cut(sim)
    best = lambda k: F.row_number().over(Window.partitionBy(k).orderBy(F.desc("sim"), "pair_id")) == 1
    ranked = sim.withColumn("mutual", best("left_id") & best("right_id"))
    stat = ranked.where("mutual").agg((F.avg("sim") - F.stddev_pop("sim")).alias("tau"))
    return ranked.crossJoin(F.broadcast(stat)).withColumn("pred", (F.col("mutual") & (F.col("sim") >= F.coalesce("tau", F.lit(0.0)))).cast("int")).drop("tau", "mutual")


def match_mlp(scored: DataFrame, dim: int = 32, seed: int = 7) -> DataFrame:
    """The supervised form: a small network on |u - v| and u x v; scored has u, w, y, role ('label' rows train; without any, no pair matches)."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier
    from pyspark.ml.functions import array_to_vector

    zero = F.array_repeat(F.lit(0.0), dim)
    u, w = F.coalesce("u", zero), F.coalesce("w", zero)
    feats = scored.withColumn("features", array_to_vector(F.concat(F.zip_with(u, w, lambda a, b: F.abs(a - b)), F.zip_with(u, w, lambda a, b: a * b))))
    train = feats.where("role = 'label'").withColumn("label", F.col("y").cast("double"))
    if not train.head(1):
        return scored.withColumn("pred", F.lit(0))
    model = MultilayerPerceptronClassifier(layers=[2 * dim, 16, 2], maxIter=60, seed=seed).fit(train)
    return model.transform(feats).withColumn("pred", F.col("prediction").cast("int")).drop("features", "rawPrediction", "probability", "prediction")
