from pyspark.sql import functions as F

from pairmatch.operators import blocking as B, graph_walk as G
from pairmatch.operators.relational import as_of, near_copies


def test_first_steps_and_hubs(spark):
    left = spark.createDataFrame([("1", "red fox"), ("2", "red hen")], "id string, seq string")
    right = spark.createDataFrame([("a", "fox den"), ("b", "hen")], "id string, seq string")
    g = G.edges(left, right, max_degree=2)
    assert {(r.src, r.dst) for r in g.collect() if not r.src.startswith("w:")} == {("L:1", "w:red"), ("L:1", "w:fox"), ("L:2", "w:red"), ("L:2", "w:hen"), ("R:a", "w:fox"), ("R:b", "w:hen")}
    w = G.walks(g, 2, 4)
    assert w.groupBy("walk").count().where("count <> 4").count() == 0
    edges = {(r.src, r.dst) for r in g.collect()}
    by = {}
    for r in w.collect():
        by.setdefault(r.walk, {})[r.step] = r.node
    assert all((x[i], x[i + 1]) in edges for x in by.values() for i in range(3))


def test_as_of_takes_the_latest_not_after(spark):
    a = spark.createDataFrame([(1, 10), (1, 4), (2, 10)], "k int, t int")
    b = spark.createDataFrame([(1, 3, "x"), (1, 10, "y"), (1, 11, "z")], "k int, u int, v string")
    assert {(r.k, r.t): r.v for r in as_of(a, b, "k", "t", "u", "v").collect()} == {(1, 10): "y", (1, 4): "x", (2, 10): None}


def test_near_copies_and_blocks_keep_all_true_pairs(spark):
    words = [f"w{i}" for i in range(40)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join([*words[:39], "z"])), (3, " ".join(reversed(words))), (4, None)], "doc_id long, text string")
    assert [(r.left_id, r.right_id, r.shared, r.united) for r in near_copies(docs, 70).collect()] == [(1, 2, 37, 39)]
    p = spark.createDataFrame([("a", 0.0, 0.0), ("b", 0.9, -0.9), ("c", 5.0, 5.0)], "id string, lat double, lon double")
    assert {(r.left_id, r.right_id) for r in B.block_grid(p, p, "lat", "lon", 1.0, 1.0).where("left_id < right_id").collect()} == {("a", "b")}
    s = p.withColumn("n", F.expr("int(lat * 100)"))
    assert {(r.left_id, r.right_id) for r in B.block_sorted(s, s, F.col("n"), 90, 8).where("left_id < right_id").collect()} == {("a", "b")}


def _edges_of(pairs):
    n = {}
    for r in pairs.collect():
        n[("left", r.left_id)] = n.get(("left", r.left_id), 0) + 1
        n[("right", r.right_id)] = n.get(("right", r.right_id), 0) + 1
    return n


def test_links_are_those_of_the_pairs(spark):
    import random

    rng = random.Random(3)
    a, b = (spark.createDataFrame([(f"{s}{i}", rng.choice(["x", "y", "z", None]), rng.randrange(-300, 300) if i else None) for i in range(60)], "id string, block string, n int") for s in "ab")
    want = _edges_of(B.block_equi(a.where("block is not null"), b, ["block"]))
    assert {(r.side, r.id): r.links for r in B.equi_links(a, b, ["block"]).collect() if r.links} == want
    assert B.equi_links(a, b, ["block"]).count() == 120
    for width, bucket in ((7, 8), (50, 64), (90, 8)):
        met = B.block_sorted(a, a, F.col("n"), width, bucket).where("left_id <> right_id").groupBy("left_id").count()
        assert {r.id: r.links for r in B.sorted_links(a, F.col("n"), width, bucket).collect() if r.links} == {r.left_id: r["count"] for r in met.collect()}
        assert B.sorted_links(a, F.col("n"), width, bucket).count() == 60


def test_large_blocks_are_counted_not_paired(spark):
    one = lambda n: spark.range(n).select(F.col("id").cast("string").alias("id"), F.col("id").alias("key"), F.lit("b").alias("block"), F.lit(5).alias("n"))
    n = 300_000
    assert B.equi_counts(one(n), one(n)).first()[:] == (n * n, n)
    assert B.equi_links(one(n), one(n), ["block"]).agg(F.count("*"), F.sum("links")).first()[:] == (2 * n, 2 * n * n)
    assert B.sorted_links(one(n), F.col("n"), 3).agg(F.count("*"), F.min("links")).first()[:] == (n, n - 1)


def test_counts_with_repeated_ids(spark):
    schema = "id string, key long, block string"
    a = [("1", 1, "x"), ("1", 1, "y"), ("2", 2, "x"), ("3", 3, None), ("4", 4, "y"), ("4", 5, "y"), (None, 9, "x")]
    b = [("1", 1, "x"), ("1", 1, "y"), ("2", 2, "y"), ("4", 4, "y"), ("5", None, "x")]
    want = {(i, j, None if k is None or m is None else int(k == m)) for i, k, x in a for j, m, y in b if x is not None and x == y}
    got = B.equi_counts(spark.createDataFrame(a, schema), spark.createDataFrame(b, schema)).first()
    assert got[:] == (len(want), sum(t or 0 for *_, t in want))


def test_copies_have_a_row_each_and_no_link_between_texts_is_lost(spark):
    """A thousand copies of one text give a row each, not half a million, and links of other texts stay."""
    import random

    rng = random.Random(4)
    base = [f"v{rng.randrange(500)}" for _ in range(60)]
    texts = [" ".join(base)] * 1000 + ["two words", "", None, "a a a a a"]
    for k in range(60):
        x = list(base)
        for at in rng.sample(range(60), rng.randrange(1, 12)):
            x[at] = f"z{k}x{at}" if rng.random() < 0.7 else "a"
        texts.append(" ".join(x))
    got = {(r.left_id, r.right_id): (r.shared, r.united) for r in near_copies(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), 40).collect()}
    sets = [frozenset(tuple(w[i : i + 3]) for i in range(len(w) - 2)) for w in ((t or "").split() for t in texts)]
    first = {}
    for i, g in enumerate(sets):
        first.setdefault(g, i)
    want = {(first[g], i): (len(g), len(g)) for i, g in enumerate(sets) if g and first[g] != i}
    reps = [(i, g) for g, i in first.items() if g]
    for i, g in reps:
        for j, h in reps:
            if i < j and len(g & h) * 100 >= len(g | h) * 40:
                want[i, j] = (len(g & h), len(g | h))
    assert got == want and len(got) > 1050
