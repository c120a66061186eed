from pairmatch.operators.estimator import PairMatcher, register


def test_stage_fits_and_transforms(spark):
    rows = [(f"{i}", f"red fox {i}", f"red fox {i}" if i % 2 else f"blue hen {i + 50}", i % 2) for i in range(40)]
    df = spark.createDataFrame(rows, "pair_id string, left_seq string, right_seq string, y int")
    out = PairMatcher().fit(df).transform(df)
    assert out.where("pred <> y").count() == 0 and set(df.columns) < set(out.columns)


def test_sql_functions(spark):
    register(spark)
    assert spark.sql("select token_jaccard('a b c', 'b c d')").first()[0] == 0.5
    assert spark.sql("select cloze_evidence('a b', 'a b')").first()[0][0] == 10
    assert [tuple(r) for r in spark.sql("select * from explain_pair('a b', 'b c')").collect()] == [("a", True, False), ("b", True, True), ("c", False, True)]
