"""Joins and set operators around matching that Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pairmatch.plans.dialect import spark_sql
from pairmatch.plans.session import cut
from pairmatch.sources.workloads import run_sql


def as_of(left: DataFrame, right: DataFrame, by: str, at_left: str, at_right: str, value: str) -> DataFrame:
    """left with the right side's value of the latest row of its key not after its time.

    Both sides are put in one time order per key, so each is shuffled once and no pair
    that is not wanted is made; ties at one time take the right row first.
    """
    a = left.withColumns({"_t": F.col(at_left), "_side": F.lit(1), "_v": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(F.col(by), F.col(at_right).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    w = Window.partitionBy(by).orderBy("_t", "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True).withColumn("_last", F.last("_v", ignorenulls=True).over(w))
    return both.where("_side = 1").select(*left.columns, F.col("_last").alias(value))


def containment(spark: SparkSession, d: str, sample: int = 10) -> DataFrame:
    """left_id (item), right_id (document), y: whether the document has the item's words in a row.

    Items meet documents on a shared five-word shingle (those of fewer words take no such
    part); those met that lack the rest, and `sample` documents at the ranks that follow a
    hashed one, are the others. No item meets all documents.
    """
    from pairmatch.sources.workloads import numbered

    grams = lambda t, i: run_sql(spark, d, f"select STR({i}) as id, GRAMS(t, 5) as g, ' ' || JOIN(t) || ' ' as s from (select {i}, TOK(text) as t from {{{t}}}) q_")
    items, docs = grams("benchmark", "item_id"), grams("documents", "doc_id")
    a = items.select(F.col("id").alias("left_id"), F.explode_outer(F.array_distinct("g")).alias("x")).where("x is not null")
    b = docs.select(F.col("id").alias("right_id"), F.explode_outer(F.array_distinct("g")).alias("x")).where("x is not null")
    met = a.join(b, "x").select("left_id", "right_id").distinct()
    ranked, sizes = numbered(docs.select("id", F.lit(0).alias("key"), F.lit(0).alias("block")))
    asked = items.select("id").crossJoin(sizes.select("size_"))  # one row
    asked = asked.withColumn("j_", F.explode(F.sequence(F.lit(0), F.least(F.col("size_"), F.lit(sample)) - 1)))
    some = asked.select(F.col("id").alias("left_id"), F.expr(spark_sql("(H('neg|' || id) + j_) % size_")).alias("rank")).join(ranked.select(F.col("id").alias("right_id"), "rank"), "rank").select("left_id", "right_id")
    both = met.unionByName(some).distinct()
    texts = both.join(items.select(F.col("id").alias("left_id"), F.col("s").alias("s1")), "left_id").join(docs.select(F.col("id").alias("right_id"), F.col("s").alias("s2")), "right_id")
    return texts.select("left_id", "right_id", F.col("s2").contains(F.col("s1")).cast("int").alias("y"))


BUCKETS = 1 << 20  # hashes of grams are counted in so many


def near_copies(docs: DataFrame, floor_percent: int = 70) -> DataFrame:
    """left_id, right_id, shared, united for documents whose word three-grams overlap at least so much, exactly.

    Documents of one set of grams are a class, its smallest id stands for it: pairs are
    those of such ids, and each other member has one row with its own. Pairs meet on shared
    grams of a prefix of each set in a global order, long enough that no pair over the floor
    can miss, and are confirmed on their texts. The order is by the size of a bucket of
    hashes, then hash: any order that all documents share loses nothing, and this one needs
    no exchange of all grams (equal hashes of different grams only add candidates).
    """
    spark = docs.sparkSession
    grams = lambda c: F.array_distinct(F.expr(spark_sql(f"GRAMS({c}, 3)")))
    cut_up = lambda x: x.select("doc_id", F.expr(spark_sql("TOK(text)")).alias("t")).select("doc_id", grams("t").alias("g"))
    members = cut(cut_up(docs).select("doc_id", F.size("g").alias("n"), F.sha2(F.array_join(F.array_sort("g"), "\n"), 256).alias("key"))).where("n > 0")
    classes = members.groupBy("key").agg(F.min("doc_id").alias("rep"))
    firsts = docs.join(classes.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi").select("doc_id", "text")
    hashed = cut_up(firsts).select("doc_id", F.size("g").alias("n"), F.array_distinct(F.transform("g", lambda x: F.xxhash64(x))).alias("h"))
    head = _prefixes(hashed, floor_percent, spark)
    a, b = head.withColumnsRenamed({"doc_id": "left_id", "n": "na"}), head.withColumnsRenamed({"doc_id": "right_id", "n": "nb"})
    size = F.least("na", "nb") * 100 >= F.greatest("na", "nb") * floor_percent
    pairs = a.join(b, "x").where((F.col("left_id") < F.col("right_id")) & size).select("left_id", "right_id").distinct()
    words = lambda i, s: firsts.select(F.col("doc_id").alias(i), F.col("text").alias(s))
    full = pairs.join(words("left_id", "sa"), "left_id").join(words("right_id", "sb"), "right_id")
    sets = full.select("left_id", "right_id", *[F.expr(spark_sql(f"TOK({c})")).alias(t) for c, t in (("sa", "ta"), ("sb", "tb"))]).select("left_id", "right_id", grams("ta").alias("ga"), grams("tb").alias("gb"))
    sizes = F.struct(F.size("ga").alias("na"), F.size("gb").alias("nb"), F.size(F.array_intersect("ga", "gb")).alias("shared"))
    one = sets.select("left_id", "right_id", F.explode_outer(F.array(sizes)).alias("m")).select("left_id", "right_id", "m.*")  # no filter goes below explode_outer
    near = one.select("left_id", "right_id", "shared", (F.col("na") + F.col("nb") - F.col("shared")).alias("united")).where(F.col("shared") * 100 >= F.col("united") * floor_percent)
    same = members.join(classes, "key").where("doc_id <> rep").select(F.col("rep").alias("left_id"), F.col("doc_id").alias("right_id"), F.col("n").alias("shared"), F.col("n").alias("united"))
    return near.unionByName(same)


def _prefixes(hashed: DataFrame, floor_percent: int, spark: SparkSession) -> DataFrame:
    """doc_id, n, x: the first hashes of each document (doc_id, n, h) in the order of their buckets' sizes."""
    import numpy as np
    import pyarrow as pa

    found = hashed.select(F.explode_outer("h").alias("x")).where("x is not null").groupBy(F.col("x").bitwiseAND(BUCKETS - 1).cast("int").alias("b")).agg(F.count("*").alias("c")).toArrow()  # BUCKETS rows at most
    sizes = np.zeros(BUCKETS, dtype=np.int64)
    sizes[found["b"].to_numpy()] = found["c"].to_numpy()
    shared, mask = spark.sparkContext.broadcast(sizes), BUCKETS - 1

    def run(batches):
        at = shared.value
        for batch in batches:
            ids, ns, h = batch.column(0), batch.column(1).to_numpy(), batch.column(2)
            offsets, flat = h.offsets.to_numpy(), h.values.to_numpy()
            row, out = [], []
            for i, n in enumerate(ns):
                x = flat[offsets[i] : offsets[i + 1]]
                keep = np.lexsort((x, at[x & mask]))[: n + (-n * floor_percent) // 100 + 1]
                row.append(np.full(len(keep), i))
                out.append(x[keep])
            take = np.concatenate([np.zeros(0, dtype=np.int64), *row])
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(take)), pa.array(ns[take], pa.int32()), pa.array(np.concatenate([np.zeros(0, dtype=np.int64), *out]), pa.int64())], ["doc_id", "n", "x"])

    return hashed.mapInArrow(run, "doc_id long, n int, x long")
