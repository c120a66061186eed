"""Further queries of records and relational operators, and their SQL twins."""

from __future__ import annotations

from pyspark.sql import Window, functions as F

from pairmatch import oracles as O
from pairmatch.functions.serialize import serialize
from pairmatch.functions.templates import Template
from pairmatch.plans.dialect import duck_sql
from pairmatch.sources import workloads as W

CUSTOMERS = W.Side(
    "select STR(c_custkey) as id, c_custkey as key, STR(c_nationkey) as block, case when c_custkey % 3 = 0 then null else c_name end as name, case when c_custkey % 5 = 0 then null else c_mktsegment end as segment, DEC(c_acctbal) as balance from {customer}",
    (("name", "name"), ("segment", "segment"), ("balance", "balance")), "rel",
)


def _t(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


def ser_rel_customer_nulls(spark, d):
    return serialize(W.side_records(spark, d, CUSTOMERS), "rec", "rel").select("id", "seq")


def ser_semi_event_json(spark, d):
    """Open records: the JSON column read as a variant."""
    k = F.variant_get(F.parse_json("props"), "$.k", "int")
    e = _t(spark, d, "events").select(F.col("event_id").cast("string").alias("id"), F.struct(F.col("event_type").alias("kind"), F.struct(k.alias("k")).alias("props")).alias("rec"))
    return serialize(e, "rec", "semi").select("id", "seq")


EVENT_JSON = "select event_id::varchar as id, '[COL] kind [VAL] ' || event_type || ' [COL] props [VAL] [COL] k [VAL] ' || (props->>'$.k') as seq from events"


def prompt_slot_position(spark, d):
    left, right = W.sequences(spark, d, "w4")
    p = W.attach(W.pairs(spark, d, "w4"), left, right)
    at = lambda s: Template(s, "hard").slot_position(F.col("left_seq"), F.col("right_seq"))
    return p.select("pair_id", at("t1").alias("t1_slot"), at("t2").alias("t2_slot"))


SLOT = f"with {O.pairs_cte('w4')} select pair_id, (len(string_split(left_seq, ' ')) + len(string_split(right_seq, ' ')) + 2)::int as t1_slot, (len(string_split(left_seq, ' ')) + 1)::int as t2_slot from pairs"


def window_ranks_events(spark, d):
    by = Window.partitionBy("event_type")
    whole = F.floor("value").cast("long")
    e = _t(spark, d, "events").withColumn("whole", whole)
    order = by.orderBy("whole")
    return e.select(
        "event_id", F.dense_rank().over(order).alias("dense"), F.round(F.percent_rank().over(order), 6).alias("share"), F.lead("event_id").over(by.orderBy("whole", "event_id")).alias("after"),
        F.count(F.lit(1)).over(order.rangeBetween(-5, 5)).alias("near"),
    )


RANKS = """with e as (select event_id, event_type, floor(value)::bigint as whole from events)
select event_id, (dense_rank() over (partition by event_type order by whole))::int as dense, round(percent_rank() over (partition by event_type order by whole), 6) as share,
  lead(event_id) over (partition by event_type order by whole, event_id) as after, count(*) over (partition by event_type order by whole range between 5 preceding and 5 following) as near from e"""


def unpivot_document_lengths(spark, d):
    g = _t(spark, d, "documents").groupBy("lang").agg(F.min("n_chars").cast("long").alias("least"), F.max("n_chars").cast("long").alias("most"), F.count("*").alias("rows"))
    return g.unpivot(["lang"], ["least", "most", "rows"], "what", "amount")


UNPIVOT = "with g as (select lang, min(n_chars)::bigint as least, max(n_chars)::bigint as most, count(*) as n from documents group by lang) select lang, 'least' as what, least as amount from g union all select lang, 'most', most from g union all select lang, 'rows', n from g"


def map_role_turns(spark, d):
    """Maps: turns of each role by conversation, doubled, those of one turn left out."""
    n = _t(spark, d, "conversations").groupBy("conv_id", "role").agg(F.count("*").alias("n"))
    m = n.groupBy("conv_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("role", "n")))).alias("m"))
    kept = F.map_concat(F.transform_values(F.map_filter("m", lambda k, v: v > 1), lambda k, v: v * 2), F.create_map(F.lit("all"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x)))
    return m.select("conv_id", F.explode(kept).alias("role", "amount"))


ROLES = "with n as (select conv_id, role, count(*) as n from conversations group by 1, 2) select conv_id, role, n * 2 as amount from n where n > 1 union all select conv_id, 'all', sum(n)::bigint from n group by 1"


def approximate_within_tolerance(spark, d):
    """Whether approximate aggregates are within their stated error of the exact ones."""
    p = _t(spark, d, "part").agg(F.approx_count_distinct("p_retailprice", 0.02).alias("a"), F.count_distinct("p_retailprice").alias("e"), F.percentile_approx("p_size", 0.5, 10000).alias("q"), F.percentile("p_size", F.lit(0.5)).alias("x"))
    ok = lambda a, e, r: F.abs(F.col(a) - F.col(e)) <= F.greatest(F.col(e) * r, F.lit(1))
    return p.select(F.explode(F.array(F.struct(F.lit("distinct").alias("what"), ok("a", "e", 0.08).alias("ok")), F.struct(F.lit("median").alias("what"), ok("q", "x", 0.02).alias("ok")))).alias("r")).select("r.*")


APPROXIMATE = "select 'distinct' as what, true as ok union all select 'median', true"

PAIRS_W10 = duck_sql(f"""with i as (select STR(item_id) as id, GRAMS(t, 5) as g, ' ' || JOIN(t) || ' ' as s from (select item_id, TOK(text) as t from benchmark) q_),
d as (select STR(doc_id) as id, GRAMS(t, 5) as g, ' ' || JOIN(t) || ' ' as s from (select doc_id, TOK(text) as t from documents) q_),
met as (select distinct i.id as left_id, d.id as right_id from (select id, unnest(g) as x from i) i join (select id, unnest(g) as x from d) d on i.x = d.x),
ranked as (select id, row_number() over (order by H('rank|' || id), id) - 1 as rank_, count(*) over () as size_ from d),
asked as (select id, unnest(generate_series(0, least((select count(*) from d), 10) - 1)) as j_ from i),
extra as (select asked.id as left_id, ranked.id as right_id from asked join ranked on ranked.rank_ = (H('neg|' || asked.id) + asked.j_) % ranked.size_),
both_ as (select * from met union select * from extra),
judged as (select left_id, right_id, contains(d.s, i.s)::int as y from both_ join i on i.id = left_id join d on d.id = right_id),
cut as (select *, row_number() over (partition by left_id, y order by H('neg|' || left_id || '|' || right_id), right_id) as n_ from judged)
select left_id || '|' || right_id as pair_id, y, {O.SPLIT} as split from cut where y = 1 or n_ <= 10""")


def queries() -> dict:
    return {f.__name__: f for f in (ser_rel_customer_nulls, ser_semi_event_json, prompt_slot_position, window_ranks_events, unpivot_document_lengths, map_role_turns, approximate_within_tolerance)}


def oracles() -> dict[str, str]:
    return {
        "ser_rel_customer_nulls": f"select id, seq from ({O.seq_of(CUSTOMERS)})", "ser_semi_event_json": EVENT_JSON, "prompt_slot_position": SLOT, "window_ranks_events": RANKS,
        "unpivot_document_lengths": UNPIVOT, "map_role_turns": ROLES, "approximate_within_tolerance": APPROXIMATE, "pairs_w10": PAIRS_W10,
    }
