"""Candidate generation ahead of matching, and what it loses.

Every blocker is an equi-join on derived keys with a residual condition, so that none
degenerates into a comparison of all records with all. `max_df` leaves out keys that too
many records share (they tell nothing apart); what that costs shows in block_quality.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from pairmatch.plans.dialect import spark_sql


def cap_per_left(met: DataFrame, per_left: int) -> DataFrame:
    """Of each left record the true partners first, then others by hash; needs left_id, right_id and y."""
    order = [F.desc("y"), F.expr(spark_sql("H('neg|' || left_id || '|' || right_id)")), "right_id"]
    return met.withColumn("r", F.row_number().over(Window.partitionBy("left_id").orderBy(*order))).where(F.col("r") <= per_left).drop("r")


def cap_others(met: DataFrame, per_left: int) -> DataFrame:
    """All true partners of each left record, and of the others so many by hash."""
    order = [F.expr(spark_sql("H('neg|' || left_id || '|' || right_id)")), "right_id"]
    return met.withColumn("r", F.row_number().over(Window.partitionBy("left_id", "y").orderBy(*order))).where((F.col("y") == 1) | (F.col("r") <= per_left)).drop("r")


def _sides(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    return left.select(F.col("id").alias("left_id"), key).join(right.select(F.col("id").alias("right_id"), key), key).select("left_id", "right_id").distinct()


def block_equi(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """Records that agree on all keys."""
    name = "_block"
    both = [x.withColumn(name, F.struct(*keys)) for x in (left, right)]
    return _sides(*both, name)


def equi_links(left: DataFrame, right: DataFrame, keys: list[str]) -> DataFrame:
    """side, id, the keys, links: every record with its class (the keys' values) and the other side's records in it.

    The same links as block_equi without writing them out: a class of n and m records
    costs n + m rows in place of n times m. A record with an empty key, or alone, has 0.
    """
    a, b = (x.select("id", *keys).distinct() for x in (left, right))
    sized = lambda x: x.where(" and ".join(f"{k} is not null" for k in keys)).groupBy(*keys).agg(F.count("*").alias("links"))
    met = lambda x, y, side: x.join(sized(y), keys, "left").select(F.lit(side).alias("side"), "id", *keys, F.coalesce("links", F.lit(0)).cast("long").alias("links"))
    return met(a, b, "left").unionByName(met(b, a, "right"))


def block_tokens(left: DataFrame, right: DataFrame, col: str, max_df: int = 50, shared: int = 2) -> DataFrame:
    """Records that share at least so many tokens, none of which more than max_df records of a side have."""
    tok = lambda x, i: x.select(F.col("id").alias(i), F.explode_outer(F.array_distinct(F.expr(spark_sql(f"TOK({col})")))).alias("w")).where("w is not null")
    a, b = tok(left, "left_id"), tok(right, "right_id")
    rare = lambda x: x.groupBy("w").agg(F.count("*").alias("n")).where(F.col("n") <= max_df).select("w")
    keep = rare(a).join(rare(b), "w")
    return a.join(keep, "w").join(b, "w").groupBy("left_id", "right_id").agg(F.count("*").alias("n")).where(F.col("n") >= shared).select("left_id", "right_id")


def block_minhash(left: DataFrame, right: DataFrame, col: str, bands: int = 8, rows: int = 2) -> DataFrame:
    """Banded MinHash of word three-grams, all in expressions."""
    def keyed(x: DataFrame, i: str) -> DataFrame:
        grams = F.array_distinct(F.expr(spark_sql("GRAMS(t, 3)")))
        each = x.select("id", F.expr(spark_sql(f"TOK({col})")).alias("t")).select(F.col("id").alias(i), F.explode_outer(grams).alias("g")).where("g is not null")
        mins = [F.min(F.xxhash64("g", F.lit(j))).alias(f"m{j}") for j in range(bands * rows)]
        sig = each.groupBy(i).agg(*mins)
        band = F.array(*[F.xxhash64(F.lit(b), *[F.col(f"m{b * rows + r}") for r in range(rows)]) for b in range(bands)])
        return sig.select(i, F.explode(band).alias("k"))

    return keyed(left, "left_id").join(keyed(right, "right_id"), "k").select("left_id", "right_id").distinct()


def block_grid(left: DataFrame, right: DataFrame, lat: str, lon: str, cell: float, radius: float) -> DataFrame:
    """Points within radius (per axis), by cells and their neighbours."""
    at = lambda c: F.floor(F.col(c) / cell)
    near = F.array(F.lit(-1), F.lit(0), F.lit(1))
    a = left.select(F.col("id").alias("left_id"), F.col(lat).alias("la"), F.col(lon).alias("lo"), at(lat).alias("x"), at(lon).alias("y"))
    b = right.select(F.col("id").alias("right_id"), F.col(lat).alias("lb"), F.col(lon).alias("ob"), at(lat).alias("bx"), at(lon).alias("by"))
    b = b.select("right_id", "lb", "ob", "by", F.explode(F.transform(near, lambda i: i + F.col("bx"))).alias("x")).select("right_id", "lb", "ob", "x", F.explode(F.transform(near, lambda i: i + F.col("by"))).alias("y"))
    return a.join(b, ["x", "y"]).where((F.abs(F.col("la") - F.col("lb")) <= radius) & (F.abs(F.col("lo") - F.col("ob")) <= radius)).select("left_id", "right_id").distinct()


def block_sorted(left: DataFrame, right: DataFrame, key: Column, width: int, bucket: int = 64) -> DataFrame:
    """Records of integer sort keys at most width apart: buckets of width, own and next."""
    a = left.select(F.col("id").alias("left_id"), key.alias("ka"))
    b = right.select(F.col("id").alias("right_id"), key.alias("kb"))
    size = max(width, bucket)
    a = a.withColumn("k", F.floor(F.col("ka") / size))
    b = b.withColumn("k", F.explode(F.sequence(F.floor((F.col("kb") - width) / size), F.floor((F.col("kb") + width) / size))))
    return a.join(b, "k").where(F.abs(F.col("ka") - F.col("kb")) <= width).select("left_id", "right_id").distinct()


def sorted_links(records: DataFrame, key: Column, width: int, bucket: int = 64) -> DataFrame:
    """id, class_id, links: every record with its integer sort key and the number of others at most width apart.

    Records of one key are a class. Classes meet in buckets of the key, each bucket with
    what lies width around it, and a moving frame sums their sizes: neither copies nor
    near keys are paired.
    """
    rows = records.select("id", key.cast("long").alias("class_id")).distinct()
    sizes = rows.where("class_id is not null").groupBy("class_id").agg(F.count("*").alias("n"))
    size = max(width, bucket)
    at = lambda c: F.floor(c / size)
    spread = sizes.select("class_id", "n", F.explode(F.sequence(at(F.col("class_id") - width), at(F.col("class_id") + width))).alias("k"))
    frame = Window.partitionBy("k").orderBy("class_id").rangeBetween(-width, width)
    around = spread.withColumn("around", F.sum("n").over(frame)).where(F.col("k") == at(F.col("class_id"))).select("class_id", "around")
    return rows.join(around, "class_id", "left").select("id", "class_id", (F.coalesce("around", F.lit(1)) - 1).cast("long").alias("links"))


def block_vectors(left: DataFrame, right: DataFrame, col: str, threshold: float, length: float = 4.0, tables: int = 4, seed: int = 7) -> DataFrame:
    """Vectors within a distance, by random projections of the built-in hashing."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = lambda x: x.select("id", array_to_vector(F.col(col).cast("array<double>")).alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=length, numHashTables=tables, seed=seed).fit(v(left))
    met = model.approxSimilarityJoin(v(left), v(right), threshold, "dist")
    return met.select(F.col("datasetA.id").alias("left_id"), F.col("datasetB.id").alias("right_id"))


def equi_counts(left: DataFrame, right: DataFrame) -> DataFrame:
    """candidates, found: distinct pairs of ids that share a block, and those of one key; from id, key and block.

    Pairs of ids with a single row each are counted by the sizes of their blocks; only ids
    with several keys or blocks are paired, so that no pair counts twice.
    """
    rows, once, more = [], [], []
    for x in (left, right):
        d = x.select("id", "key", "block").where("block is not null").distinct()
        n = d.groupBy("id").agg(F.count("*").alias("n"), F.first("key").alias("key"), F.first("block").alias("block"))
        rows.append(d)
        once.append(n.where("n = 1").select("id", "key", "block"))
        many = n.where("n > 1").select(F.col("id").alias("i"))
        more.append(d.join(many, F.col("id").eqNullSafe(F.col("i")), "left_semi"))
    by = lambda keys: [x.groupBy(*keys).agg(F.count("*").alias(n)) for x, n in zip(once, ("a", "b"))]
    total = lambda keys, name: by(keys)[0].join(by(keys)[1], keys).agg(F.sum(F.col("a") * F.col("b")).alias(name))
    named = lambda x, s: x.select(F.col("id").alias(f"{s}_id"), F.col("key").alias(f"{s}_key"), "block")
    met = lambda x, y: named(x, "left").join(named(y, "right"), "block").select("left_id", "right_id", (F.col("left_key") == F.col("right_key")).cast("int").alias("t"))
    rest = met(more[0], rows[1]).unionByName(met(once[0], more[1])).distinct().agg(F.count("*").alias("c"), F.sum("t").alias("f"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long")
    one = total(["block"], "candidates").crossJoin(total(["block", "key"], "found")).crossJoin(rest)  # a row each
    return one.select((zero("candidates") + zero("c")).alias("candidates"), (zero("found") + zero("f")).alias("found"))


def block_quality(candidates: DataFrame, truth: DataFrame, n_left: int, n_right: int) -> DataFrame:
    """Share of true pairs kept and share of all pairs avoided."""
    kept = candidates.join(truth.select("left_id", "right_id").withColumn("t", F.lit(1)), ["left_id", "right_id"], "left")
    one = kept.agg(F.count("*").alias("candidates"), F.coalesce(F.sum("t"), F.lit(0)).alias("found"))
    return quality_of(one, truth, n_left, n_right)


def quality_of(one: DataFrame, truth: DataFrame, n_left: int, n_right: int) -> DataFrame:
    """The measures from a row with candidates and found."""
    return one.crossJoin(truth.agg(F.count("*").alias("true_pairs"))).select(
        "candidates", "found", "true_pairs", F.round(F.try_divide(F.col("found").cast("double"), F.col("true_pairs")), 6).alias("completeness"),
        F.round(1 - F.col("candidates") / (float(n_left) * n_right), 6).alias("reduction"),
    )
