from pyspark.sql import functions as F

from pairmatch.functions.serialize import encode_pair, serialize, truncate_pair
from pairmatch.functions.templates import Template, Verbalizer, class_scores


def one(df):
    return df.first()[0]


def test_relational_and_nested(spark):
    df = spark.sql("select named_struct('name', 'deep  sea', 'year', 1999, 'price', 12.5D, 'note', cast(null as string)) as r")
    assert one(serialize(df, "r", "rel").select("seq")) == "[COL] name [VAL] deep sea [COL] year [VAL] 1999 [COL] price [VAL] 12.50 [COL] note [VAL] "
    df = spark.sql("select named_struct('t', 'x', 'who', named_struct('a', array('ann', 'bo'), 'n', cast(null as int)), 'l', array(named_struct('p', 1, 'q', 'z'))) as r")
    assert one(serialize(df, "r", "semi").select("seq")) == "[COL] t [VAL] x [COL] who [VAL] [COL] a [VAL] ann bo [COL] l [VAL] 1 z"
    assert "[COL] p [VAL] 1" in one(serialize(df, "r", "semi", lists="tagged").select("seq"))


def test_tags_in_values_are_escaped_and_maps_sorted(spark):
    df = spark.sql("select named_struct('v', 'see [COL] here', 'm', map('b', '2', 'a', '1'), 'e', cast(array() as array<string>)) as r")
    assert one(serialize(df, "r", "semi").select("seq")) == r"[COL] v [VAL] see \[COL\] here [COL] m [VAL] [COL] a [VAL] 1 [COL] b [VAL] 2 [COL] e [VAL] "


def test_pair_and_truncation(spark):
    df = spark.sql("select 'a b c d e f' as l, 'x y' as r")
    assert one(df.select(encode_pair(F.col("l"), F.col("r")))) == "[CLS] a b c d e f [SEP] x y [SEP]"
    a, b = truncate_pair(F.col("l"), F.col("r"), 6)
    assert df.select(a, b).first()[:] == ("a b c d", "x y")


def test_templates_and_class_scores(spark):
    df = spark.sql("select 'a b' as l, 'c' as r, array(0.4D, 0.2D, 0.0D, 0.3D, 0.0D, 0.0D) as p")
    assert one(df.select(Template("t1").apply(F.col("l"), F.col("r")))) == "a b c They are [MASK]"
    assert one(df.select(Template("t2").slot_position(F.col("l"), F.col("r")))) == 3
    no, yes = class_scores(F.col("p"), Verbalizer.general())
    assert [round(x, 6) for x in df.select(no, yes).first()] == [0.333333, 0.666667]
    no, yes = class_scores(F.col("p"), Verbalizer.general(), normalize=False)
    assert [round(x, 6) for x in df.select(no, yes).first()] == [0.1, 0.2]
