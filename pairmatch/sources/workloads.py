"""Pair workloads on the given tables: two record tables of different formats, their truth.

Each side is a query in the neutral dialect of plans.dialect with columns id, key, block
and the fields of its record. A field is an expression, a nested list of fields, or a
list-valued expression. The left side is a table's own rows, the right side a seeded
rewrite of them in another format.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from pairmatch.functions.serialize import serialize
from pairmatch.plans.dialect import spark_sql

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@dataclass(frozen=True)
class Side:
    source: str  # a query over {table} names
    fields: tuple  # (name, expression) or (name, (fields...)); empty for text in column body
    fmt: str


def dropped(salt: str, percent: int, words: str, key: str) -> str:
    """Words of a list, each left out in so many per cent of cases."""
    return f"JOIN(KEEPI(w, i, {words}, H('{salt}|' || STR({key}) || '|' || STR($i)) % 100 >= {percent}))"


def chance(salt: str, percent: int, key: str) -> str:
    return f"H('{salt}|' || STR({key})) % 100 < {percent}"


ITEMS = "select l_orderkey, SORTED(STR(l_partkey) || ' ' || STR(INT(l_quantity))) as items, count(*) as n_lines, sum(INT(l_quantity)) as qty, DAY(min(l_shipdate)) as first_day, DAY(max(l_shipdate)) as last_day from {lineitem} group by l_orderkey"
ORDERS = f"select o_orderkey, o_custkey, o_orderstatus, o_orderpriority, o_orderdate, o_totalprice, items, n_lines, qty, first_day, last_day from {{orders}} left join ({ITEMS}) x_ on l_orderkey = o_orderkey"
CUST = "select c_custkey, c_name, c_mktsegment, c_acctbal, n_name, totals from {customer} join {nation} on c_nationkey = n_nationkey left join (select o_custkey, SORTED(STR(BIG(floor(o_totalprice)))) as totals from {orders} group by o_custkey) y_ on o_custkey = c_custkey"
PAGES = "select page_id, url, EX(html, '<title>([^<]*)') as title, EX(html, 'lang=\"([a-z]+)') as lang, TOK(RX(html, '<[^>]*>', ' ')) as words from {pages}"
TURNS = "select conv_id, SORTED(STR(turn + 1000) || ' ' || role || ' ' || JOIN(HEAD(TOK(text), 8))) as turns, SORTED(STR(turn + 1000) || ' ' || text) as whole from {conversations} group by conv_id"
GEO = "select c_custkey, c_name, c_mktsegment, n_name, H('lat|' || STR(c_custkey)) % 18000 as lat, H('lon|' || STR(c_custkey)) % 36000 as lon from {customer} join {nation} on c_nationkey = n_nationkey"

SIDES: dict[str, tuple[Side, Side]] = {
    "w1": (
        Side("select STR(p_partkey) as id, p_partkey as key, p_brand || p_type as block, p_name as name, p_brand as brand, p_type as type, STR(p_size) as size, DEC(p_retailprice) as price from {part}", (("name", "name"), ("brand", "brand"), ("type", "type"), ("size", "size"), ("price", "price")), "rel"),
        Side(
            f"select STR(p_partkey) as id, p_partkey as key, p_brand || p_type as block, case when {chance('w', 20, 'p_partkey')} then RX(p_name, '^[^ ]+ ', '') else p_name end || ' ' || lower(p_type) as product, EX(p_brand, '([0-9]+)') as maker, case when {chance('s', 10, 'p_partkey')} then null when p_size <= 16 then 'small' when p_size <= 33 then 'medium' else 'large' end as size_class, STR(DIV(BIG(floor(p_retailprice)) * (100 + case when {chance('p', 30, 'p_partkey')} then H('q|' || STR(p_partkey)) % 11 - 5 else 0 end), 100)) as list_price from {{part}}",
            (("product", "product"), ("maker", "maker"), ("size_class", "size_class"), ("list_price", "list_price")), "rel",
        ),
    ),
    "w2": (
        Side(f"select STR(o_orderkey) as id, o_orderkey as key, STR(o_custkey) as block, o_orderstatus as status, o_orderpriority as priority, DAY(o_orderdate) as day, DEC(o_totalprice) as total, items from ({ORDERS}) z_", (("status", "status"), ("priority", "priority"), ("date", "day"), ("total", "total"), ("items", "items")), "semi"),
        Side(
            f"select STR(o_orderkey) as id, o_orderkey as key, STR(o_custkey) as block, case when {chance('s', 30, 'o_orderkey')} then null else o_orderstatus end as status, case when {chance('y', 30, 'o_orderkey')} then null else o_orderpriority end as priority, DAY(SHIFT(o_orderdate, H('d|' || STR(o_orderkey)) % 15 - 7)) as day, STR(DIV(BIG(floor(o_totalprice)) * (1000 + H('c|' || STR(o_orderkey)) % 21 - 10), 1000)) as total, KEEPI(w, i, items, H('i|' || STR(o_orderkey) || '|' || STR($i)) % 100 < 20) as items from ({ORDERS}) z_",
            (("status", "status"), ("priority", "priority"), ("date", "day"), ("total", "total"), ("items", "items")), "semi",
        ),
    ),
    "w3": (
        Side(f"select STR(o_orderkey) as id, o_orderkey as key, STR(o_custkey) as block, STR(o_custkey) as customer, DAY(o_orderdate) as day, DEC(o_totalprice) as total, items from ({ORDERS}) z_", (("customer", "customer"), ("date", "day"), ("total", "total"), ("items", "items")), "semi"),
        Side(
            f"select STR(o_orderkey) as id, o_orderkey as key, STR(o_custkey) as block, STR(n_lines) as n_lines, STR(qty) as qty, case when {chance('f', 50, 'o_orderkey')} then null else first_day end as first_day, last_day, STR(o_custkey) as buyer, MONTH(o_orderdate) as month, STR(BIG(floor(o_totalprice / 1000))) as total_k, case when {chance('i', 60, 'o_orderkey')} then AT(items, 1) end as sample_item from ({ORDERS}) z_",
            (("totals", (("lines", "n_lines"), ("qty", "qty"))), ("span", (("first", "first_day"), ("last", "last_day"))), ("buyer", (("key", "buyer"),)), ("month", "month"), ("total_k", "total_k"), ("sample_item", "sample_item")), "semi",
        ),
    ),
    "w4": (
        Side(f"select STR(c_custkey) as id, c_custkey as key, n_name || c_mktsegment as block, c_name as name, c_mktsegment as segment, DEC(c_acctbal) as balance, n_name as nation, totals from ({CUST}) z_", (("name", "name"), ("segment", "segment"), ("balance", "balance"), ("nation", (("name", "nation"),)), ("orders", "totals")), "semi"),
        Side(
            f"select STR(c_custkey) as id, c_custkey as key, n_name || c_mktsegment as block, case when {chance('n', 50, 'c_custkey')} then '' else c_name end as label, c_mktsegment as segment, STR(BIG(floor(c_acctbal / 100))) as balance_band, n_name as country, coalesce(JOIN(KEEPI(w, i, totals, H('o|' || STR(c_custkey) || '|' || STR($i)) % 100 < 30)), '') as spend from ({CUST}) z_",
            (("label", "label"), ("segment", "segment"), ("balance_band", "balance_band"), ("country", "country"), ("spend", "spend")), "rel",
        ),
    ),
    "w5": (
        Side(f"select STR(page_id) as id, page_id as key, lang as block, url, title, lang, HEAD(words, 12) as nav from ({PAGES}) z_", (("url", "url"), ("title", "title"), ("lang", "lang"), ("nav", "nav")), "semi"),
        Side(f"select STR(page_id) as id, page_id as key, lang as block, {dropped('t', 40, 'words', 'page_id')} as body from ({PAGES}) z_", (), "text"),
    ),
    "w6": (
        Side(f"select STR(conv_id) as id, conv_id as key, 'all' as block, turns from ({TURNS}) z_", (("turns", "turns"),), "semi"),
        Side(f"select STR(conv_id) as id, conv_id as key, 'all' as block, {dropped('t', 60, 'TOK(JOIN(whole))', 'conv_id')} as body from ({TURNS}) z_", (), "text"),
    ),
    "w7": (
        Side("select STR(doc_id) as id, doc_id as key, lang as block, lang, source, STR(n_chars) as n_chars, JOIN(HEAD(TOK(text), 12)) as lead from {documents}", (("lang", "lang"), ("source", "source"), ("n_chars", "n_chars"), ("lead", "lead")), "rel"),
        Side(f"select STR(doc_id) as id, doc_id as key, lang as block, {dropped('t', 50, 'TOK(text)', 'doc_id')} as body from {{documents}}", (), "text"),
    ),
    "w8": (
        Side(f"select STR(c_custkey) as id, c_custkey as key, STR(DIV(lat, 3000)) || '|' || STR(DIV(lon, 3000)) as block, c_name as name, DEC((lat - 9000) / 100.0) as lat, DEC((lon - 18000) / 100.0) as lon, c_mktsegment as segment, n_name as nation from ({GEO}) z_", (("name", "name"), ("lat", "lat"), ("lon", "lon"), ("segment", "segment"), ("nation", "nation")), "rel"),
        Side(
            f"select STR(c_custkey) as id, c_custkey as key, STR(DIV(lat, 3000)) || '|' || STR(DIV(lon, 3000)) as block, case when {chance('m', 40, 'c_custkey')} then '' else c_name end as label, DEC(DIV(lat + H('jx|' || STR(c_custkey)) % 41 - 20 - 9000, 10) / 10.0) || ',' || DEC(DIV(lon + H('jy|' || STR(c_custkey)) % 41 - 20 - 18000, 10) / 10.0) as position, c_mktsegment as segment, case when {chance('a', 15, 'c_custkey')} then '' else n_name end as area from ({GEO}) z_",
            (("label", "label"), ("position", "position"), ("segment", "segment"), ("area", "area")), "rel",
        ),
    ),
}
DEFAULT_RATE = {"w1": 0.10, "w2": 0.05, "w3": 0.10, "w4": 0.10, "w5": 0.10, "w6": 0.05, "w7": 0.10, "w8": 0.10}
STANDS_FOR = {"w1": "REL-HETER", "w2": "SEMI-HOMO", "w3": "SEMI-HETER", "w4": "SEMI-REL", "w5": "SEMI-TEXT-w", "w6": "SEMI-TEXT-c", "w7": "REL-TEXT", "w8": "GEO-HETER"}


def run_sql(spark: SparkSession, d: str, text: str) -> DataFrame:
    """A query of the neutral dialect over the given tables, named in braces."""
    used = {t: spark.read.parquet(f"{d}/{t}.parquet") for t in TABLES if "{" + t + "}" in text}
    return spark.sql(spark_sql(text).replace("{L}", "{{L}}").replace("{N}", "{{N}}"), **used)


def _struct(fields):
    return F.struct(*[(F.struct(*[F.col(e).alias(n) for n, e in x]) if isinstance(x, tuple) else F.col(x)).alias(name) for name, x in fields])


def side_records(spark: SparkSession, d: str, side: Side) -> DataFrame:
    """id, key, block, rec."""
    rows = run_sql(spark, d, side.source)
    return rows.select("id", "key", "block", (F.col("body") if side.fmt == "text" else _struct(side.fields)).alias("rec"))


def sequences(spark: SparkSession, d: str, w: str) -> tuple[DataFrame, DataFrame]:
    """(id, key, block, seq) of both sides."""
    return tuple(serialize(side_records(spark, d, s), "rec", s.fmt).select("id", "key", "block", "seq") for s in SIDES[w])


CELL_ROWS = 50_000  # rows of a block that one task numbers


def numbered(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """rows (id, key, block) with their rank by hash within the block, and the blocks' sizes.

    A block is numbered in ranges of the hash, so that no block, however large, is in one
    task; ranks don't depend on the number of ranges.
    """
    cells = max(1, -(-rows.count() // CELL_ROWS))
    hashed = rows.withColumn("h_", F.expr(spark_sql("H('rank|' || id)"))).withColumn("cell_", F.expr(f"h_ * {cells} div 4294967296"))
    counted = hashed.groupBy("block", "cell_").agg(F.count("*").alias("n_"))
    before = Window.partitionBy("block").orderBy("cell_").rowsBetween(Window.unboundedPreceding, -1)
    sizes = counted.withColumns({"base_": F.coalesce(F.sum("n_").over(before), F.lit(0)), "size_": F.sum("n_").over(Window.partitionBy("block"))})
    within = F.row_number().over(Window.partitionBy("block", "cell_").orderBy("h_", "id"))
    ranked = hashed.withColumn("in_", within).join(sizes.select("block", "cell_", "base_"), ["block", "cell_"])
    return ranked.select("id", "key", "block", (F.col("base_") + F.col("in_") - 1).alias("rank")), sizes.select("block", "size_").distinct()


def pairs(spark: SparkSession, d: str, w: str, per_left: int = 10) -> DataFrame:
    """pair_id, left_id, right_id, y, split of a keyed workload: the partner, and others of the block.

    The others stand at the ranks that follow a hashed one, so that a left record meets
    per_left right ones at most, whatever the size of its block.
    """
    left, right = (run_sql(spark, d, s.source).select("id", "key", "block") for s in SIDES[w])
    ranked, sizes = numbered(right)
    true = left.join(right.select(F.col("id").alias("right_id"), "key", "block"), ["block", "key"]).select(F.col("id").alias("left_id"), "right_id", F.lit(1).alias("y"))
    asked = left.join(sizes, "block").withColumn("j_", F.explode(F.sequence(F.lit(0), F.least(F.col("size_"), F.lit(per_left - 1)) - 1)))
    asked = asked.select(F.col("id").alias("left_id"), F.col("key").alias("lk"), "block", F.expr(spark_sql("(H('neg|' || id) + j_) % size_")).alias("rank"))
    others = asked.join(ranked.select(F.col("id").alias("right_id"), F.col("key").alias("rk"), "block", "rank"), ["block", "rank"])
    others = others.where(F.col("lk") != F.col("rk")).select("left_id", "right_id", F.lit(0).alias("y"))
    return with_split(true.unionByName(others))


def with_split(df: DataFrame) -> DataFrame:
    h = F.expr(spark_sql("H('split|' || left_id) % 5"))
    split = F.when(h <= 2, "train").when(h == 3, "valid").otherwise("test")
    return df.select(F.concat_ws("|", "left_id", "right_id").alias("pair_id"), "left_id", "right_id", "y", split.alias("split"))


def attach(pairs_: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Adds left_seq and right_seq."""
    return pairs_.join(left.select(F.col("id").alias("left_id"), F.col("seq").alias("left_seq")), "left_id").join(right.select(F.col("id").alias("right_id"), F.col("seq").alias("right_seq")), "right_id")




def natural_pairs(spark: SparkSession, d: str, w: str) -> DataFrame:
    """Workloads whose truth is in the data: w9 near copies, w10 relevance, w11 quality, w12 noise."""
    from pairmatch.operators.blocking import cap_others
    from pairmatch.operators.relational import containment, near_copies

    if w == "w9":
        found = near_copies(spark.read.parquet(f"{d}/documents.parquet"), floor_percent=40)
        return with_split(found.select(F.col("left_id").cast("string"), F.col("right_id").cast("string"), (F.col("shared") * 10 >= F.col("united") * 7).cast("int").alias("y")))
    if w == "w10":
        return with_split(cap_others(containment(spark, d), 10))
    if w == "w11":
        labels = spark.read.parquet(f"{d}/labels.parquet")
        return with_split(labels.select(F.col("doc_id").cast("string").alias("left_id"), F.lit("").alias("right_id"), F.col("quality").cast("int").alias("y")))
    v = spark.read.parquet(f"{d}/embeddings.parquet").select("vec_id", "label")
    other = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("vec_id").alias("o"), F.col("label").alias("ol"))
    return with_split(v.join(other, "vec_id").select(F.col("vec_id").cast("string").alias("left_id"), F.col("o").cast("string").alias("right_id"), (F.col("label") == F.col("ol")).cast("int").alias("y")))
