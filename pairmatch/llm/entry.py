"""Queries op1 to op10 on the given tables, and their SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from pairmatch.llm.common import crc_mod, table


def op1_topk_impact(spark, d):
    from pairmatch.llm.topk_impact import quantise, top_k_inner_product
    from pairmatch.llm.common import cut

    v = cut(quantise(table(spark, d, "embeddings"), "vec_id", "embedding", 1024))
    return top_k_inner_product(v, v.where("vec_id % 100 = 0"), 10)


def op2_secret_forest(spark, d):
    from pairmatch.llm.secret_forest import find_secrets

    found = find_secrets(table(spark, d, "documents"))
    return found.where("score >= 0.5").select("doc_id", "token_no", F.length("body").cast("long").alias("length"), F.sha2("body", 256).alias("digest"), F.round("score", 6).alias("score"))


def op3_best_fit_packing(spark, d):
    from pairmatch.llm.packing import pack_documents

    return pack_documents(table(spark, d, "documents"), 2048)


def op4_spaced_seeds(spark, d):
    from pairmatch.llm.decontaminate import overlaps

    found = overlaps(table(spark, d, "documents"), table(spark, d, "benchmark"))
    return found.select("doc_id", "item_id", F.col("start").cast("long"), F.col("matched").cast("long"), F.col("item_tokens").cast("long"))


def _scored(found, remainder, n):
    return found.select(
        "doc_id", (crc_mod(F.col("doc_id"), n) == remainder).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted")
    )


def op5_quality_compression(spark, d):
    from pairmatch.llm.quality_zstd import quality_scores

    return _scored(quality_scores(table(spark, d, "documents"), table(spark, d, "labels"), crc_mod(F.col("doc_id"), 4) != 2), 2, 4)


def op7_toxic_lexicon(spark, d):
    from pairmatch.llm.toxic_lexicon import toxicity_scores

    return _scored(toxicity_scores(table(spark, d, "documents"), table(spark, d, "labels"), crc_mod(F.col("doc_id"), 3) != 1), 1, 3)


def op6_minhash_bbit(spark, d):
    from pairmatch.llm.minhash_bbit import near_duplicates

    return near_duplicates(table(spark, d, "documents"), 85)


def op8_ppm_scores(spark, d):
    from pairmatch.llm.ppm_lm import score_documents

    held = crc_mod(F.col("doc_id"), 7) == 2
    found = score_documents(table(spark, d, "documents"), ~held)
    return found.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op9_warc_transactions(spark, d):
    from pairmatch.llm.warc_archive import capture_digest, captures

    return capture_digest(captures(table(spark, d, "pages")))


def op10_segment_lines(spark, d):
    from pairmatch.llm.line_dedup import ANY, duplicate_lines

    found = duplicate_lines(table(spark, d, "documents"), least_chars=ANY)
    return found.select(F.col("doc").alias("doc_id"), F.col("line_no").cast("long"), F.col("of_doc").alias("of_doc_id"), F.col("of_line_no").cast("long"), F.col("edits").cast("long"))


def llm_queries():
    return {k: v for k, v in globals().items() if k.startswith("op") and callable(v)}


OP1_SQL = """
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(1024 * x::double)::bigint) as q from embeddings
  where embedding is not null and vec_id is not null
    and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0),
s as (
  select a.vec_id as query_id, b.vec_id as vec_id,
    list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2]))::bigint as score
  from v a join v b on a.vec_id <> b.vec_id where a.vec_id % 100 = 0),
r as (select query_id, (row_number() over (partition by query_id order by score desc, vec_id))::int as rank, vec_id, score from s)
select * from r where rank <= 10
"""

OP9_SQL = """
with p as (
  select page_id, coalesce(html, '') as body, sha1(coalesce(html, '')) as h from pages where page_id is not null),
q as (
  select page_id, octet_length(encode(body))::bigint as payload_bytes,
    translate(to_base(('0x' || substr(h, 1, 10))::bigint, 32, 8) || to_base(('0x' || substr(h, 11, 10))::bigint, 32, 8)
      || to_base(('0x' || substr(h, 21, 10))::bigint, 32, 8) || to_base(('0x' || substr(h, 31, 10))::bigint, 32, 8),
      '0123456789ABCDEFGHIJKLMNOPQRSTUV', 'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567') as payload_digest from p),
f as (select *, min(page_id) over (partition by payload_digest, payload_bytes) as first_id from q)
select page_id, payload_bytes, payload_digest, case when first_id = page_id then 'response' else 'revisit' end as record_type,
  case when first_id <> page_id then first_id end as refers_to from f
"""


OP6_SQL = r"""
with recursive d as (
  select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
s as (
  select doc_id, list_distinct(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
    else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) as sh from d),
n as (select doc_id, len(sh)::bigint as n_shingles from s),
e as (select doc_id, unnest(sh) as x from s),
i as (select a.doc_id as a, b.doc_id as b, count(*) as c from e a join e b on a.x = b.x and a.doc_id <> b.doc_id group by 1, 2),
l as (select i.a, i.b from i join n p on p.doc_id = i.a join n q on q.doc_id = i.b where 100 * c >= 85 * (p.n_shingles + q.n_shingles - c)),
r as (select doc_id as a, doc_id as b from n union select r.a, l.b from r join l on r.b = l.a)
select n.doc_id, n.n_shingles, min(r.b) as component_id, n.doc_id = min(r.b) as kept
from n join r on r.a = n.doc_id group by n.doc_id, n.n_shingles
"""


OP4_SQL = r"""
with d as (select doc_id, list_filter(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') as t from documents),
b as (select item_id, list_filter(string_split_regex(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') as t from benchmark),
dt as (select doc_id, unnest(t) as w, generate_subscripts(t, 1) as p from d),
bt as (select item_id, len(t) as n, unnest(t) as w, generate_subscripts(t, 1) as q from b),
m as (select doc_id, item_id, n, n - ceil(n * 800 / 1000)::int as lost, p - q as shift, q, p from dt join bt using (w)),
k as (select distinct a.doc_id, a.item_id, a.shift from m a join m b on a.doc_id = b.doc_id and a.item_id = b.item_id and a.shift = b.shift and b.q = a.q + 1
  join m c on a.doc_id = c.doc_id and a.item_id = c.item_id and a.shift = c.shift and c.q = a.q + 2),
j as (select m.* from m join k using (doc_id, item_id, shift)),
u as (select k.doc_id, k.item_id, k.shift, j.n, least(count(distinct j.q), count(distinct j.p)) as c
  from k join j on k.doc_id = j.doc_id and k.item_id = j.item_id and j.shift between k.shift and k.shift + j.lost group by all),
g as (select *, row_number() over (partition by doc_id, item_id order by c desc, shift) as r from u where c * 1000 >= n * 800)
select doc_id, item_id, greatest(shift, 0)::bigint as start, c::bigint as matched, n::bigint as item_tokens from g where r = 1
"""


def llm_oracles():
    return {"op1_topk_impact": OP1_SQL, "op4_spaced_seeds": OP4_SQL, "op6_minhash_bbit": OP6_SQL, "op9_warc_transactions": OP9_SQL}
