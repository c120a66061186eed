"""SQL twins, built for the oracle's dialect without Spark."""

from __future__ import annotations

from pairmatch.operators.count_cloze import CLEAN, EVIDENCE, LABEL_WEIGHT, PRETEXT, WORDS, evidence_list
from pairmatch.plans.dialect import duck_sql
from pairmatch.sources.workloads import SIDES, TABLES

LISTS = {"items", "totals", "nav", "turns"}


def tables(text: str) -> str:
    for t in TABLES:
        text = text.replace("{" + t + "}", t)
    return text


def _esc(x: str) -> str:
    return f"trim(regexp_replace(regexp_replace({x}, '\\[(COL|VAL|CLS|SEP|MASK)\\]', '\\\\[\\1\\\\]', 'g'), '\\s+', ' ', 'g'))"


def seq(fields, fmt: str) -> str:
    """The tagged sequence of a record with these fields."""
    if fmt == "text":
        return "body"
    parts = []
    for name, x in fields:
        head = f"'[COL] {name} [VAL]'"
        if isinstance(x, tuple):
            parts.append(f"concat_ws(' ', {head}, {seq(x, 'semi')})")
        elif x in LISTS:
            parts.append(f"case when {x} is not null then concat_ws(' ', {head}, array_to_string(list_transform({x}, lambda e_: {_esc('e_')}), ' ')) end")
        elif fmt == "semi":
            parts.append(f"case when {x} is not null then concat_ws(' ', {head}, {_esc(x)}) end")
        else:
            parts.append(f"concat_ws(' ', {head}, coalesce({_esc(x)}, ''))")
    return f"concat_ws(' ', {', '.join(parts)})"


def side(w: str, i: int) -> str:
    return seq_of(SIDES[w][i])


def seq_of(s) -> str:
    """id, key, block and seq of a side's records."""
    return f"select id, key, block, {seq(s.fields, s.fmt)} as seq from ({tables(duck_sql(s.source))}) s_"


SPLIT = "case when H('split|' || left_id) % 5 <= 2 then 'train' when H('split|' || left_id) % 5 = 3 then 'valid' else 'test' end"


def pairs_cte(w: str, per_left: int = 10) -> str:
    """CTEs l, r and pairs (pair_id, left_id, right_id, left_seq, right_seq, y, split)."""
    rank = duck_sql("row_number() over (partition by block order by H('rank|' || id), id) - 1")
    at = duck_sql("(H('neg|' || asked_.id) + j_) % asked_.size_")
    return f"""l as ({side(w, 0)}), r as ({side(w, 1)}),
ranked_ as (select *, {rank} as rank_, count(*) over (partition by block) as size_ from r),
asked_ as (select l.id, l.key, l.block, l.seq, b_.size_, unnest(generate_series(0, least(b_.size_, {per_left - 1}) - 1)) as j_ from l join (select distinct block, size_ from ranked_) b_ on l.block = b_.block),
met as (select l.id as left_id, r.id as right_id, 1 as y, l.seq as left_seq, r.seq as right_seq from l join r on l.block = r.block and l.key = r.key
  union all select asked_.id, n_.id, 0, asked_.seq, n_.seq from asked_ join ranked_ n_ on n_.block = asked_.block and n_.rank_ = {at} where n_.key <> asked_.key),
pairs as (select left_id || '|' || right_id as pair_id, left_id, right_id, left_seq, right_seq, y::int as y, {duck_sql(SPLIT)} as split from met)"""


def evidence_cte(template: str = "t2") -> str:
    """ev (pair_id, y, split, i, f) from pairs."""
    lists = ", ".join(duck_sql(e) for e in evidence_list(template))
    return f"""tok as (select pair_id, y, split, {duck_sql(CLEAN.format('left_seq'))} as lt, {duck_sql(CLEAN.format('right_seq'))} as rt from pairs),
evl as (select pair_id, y, split, [{lists}] as ev from tok),
ev as (select pair_id, y, split, unnest(ev)::int as f, generate_subscripts(ev, 1) - 1 as i from evl)"""


def pretext_cte(template: str = "t2") -> str:
    lists = ", ".join(duck_sql(e) for e in evidence_list(template))
    return f"pre as (select word, f::int as f, count(*) as n from (select word, unnest([{lists}]) as f from ({tables(duck_sql(PRETEXT))}) p_) group by word, f)"


def model_cte(labelled: str, name: str = "m", yes=(0, 1, 2), no=(3, 4, 5)) -> str:
    """{name}w (word, f, x) and {name}p (word, p, none) from pre and a relation labelled (pair_id, y)."""
    words = f"unnest(case when b.y = 1 then {list(yes)} else {list(no)} end)"
    return f"""{name}c as (select word, f, sum(n) as n from (select word, f, n from pre union all
  select word, f, count(*) * {LABEL_WEIGHT} as n from (select {words} as word, ev.f from {labelled} b join ev on ev.pair_id = b.pair_id) group by word, f) group by word, f),
{name}t as (select word, sum(n) as t from {name}c group by word),
{name}w as (select c.word, c.f, round(ln((c.n + 1.0::double) / (t.t + 112.0::double)) * 1000000)::bigint as x from {name}c c join {name}t t on t.word = c.word),
{name}p as (select word, round(ln((t + 1.0::double) / ((select sum(t) from {name}t) + 6.0::double)) * 1000000)::bigint as p, round(ln(1.0::double / (t + 112.0::double)) * 1000000)::bigint as none from {name}t)"""


def score_cte(name: str = "m", out: str = "scored", keep: str = "", per: str = "", yes=(0, 1, 2), no=(3, 4, 5)) -> str:
    """{out} (pair_id, y, split{per}, p_yes) of every pair; keep: a condition on evidence rows."""
    group = "e.pair_id, e.y, e.split" + (f", {per}" if per else "")
    source = f"(select e.*, k as pass from ev e, range(0, 10) t_(k)) e" if per else "ev e"
    w = f"sum(case when {keep} then coalesce(w.x, p.none) else 0 end)" if keep else "sum(coalesce(w.x, p.none))"
    return f"""{out}s as (select {group.replace('e.', 'e.')}, p.word, (any_value(p.p) + {w})::bigint as s from {source} cross join {name}p p left join {name}w w on w.word = p.word and w.f = e.f group by {group}, p.word),
{out}e as (select *, exp((s - max(s) over (partition by pair_id{', pass' if per else ''})) / 1000000.0::double) as q from {out}s),
{out} as (select pair_id, y, split{', pass' if per else ''}, round((sum(case when word in {tuple(yes) if len(yes) > 1 else f'({yes[0]})'} then q else 0 end) / {len(yes)}) /
  ((sum(case when word in {tuple(yes) if len(yes) > 1 else f'({yes[0]})'} then q else 0 end) / {len(yes)}) + (sum(case when word in {tuple(no) if len(no) > 1 else f'({no[0]})'} then q else 0 end) / {len(no)})), 6) as p_yes
  from {out}e group by pair_id, y, split{', pass' if per else ''})"""


KEEP = "('0x' || substr(md5('drop0|' || e.pair_id || '|' || e.pass::varchar), e.i::int + 1, 1))::int >= 5"


def labelled_cte(rate: float, name: str = "lab") -> str:
    order = duck_sql("H('lab|' || pair_id), H('tie|' || pair_id), pair_id")
    return f"""{name} as (select pair_id, y from (select pair_id, y, row_number() over (order by {order}) as k from pairs where split = 'train')
  where k <= floor((select count(*) from pairs) * {rate} + 0.5))"""


def lowest(score: str, source: str, k: str) -> str:
    order = duck_sql(f"{score}, H('tie|' || pair_id), pair_id")
    return f"select * from (select *, row_number() over (order by {order}) as k_ from {source}) where k_ <= {k}"


def base(w: str, rate: float) -> str:
    return ",\n".join([pairs_cte(w), evidence_cte(), pretext_cte(), labelled_cte(rate), model_cte("lab")])


def unlabelled_scores(w: str, rate: float) -> str:
    """... and uns: pair_id, y, p_yes, pseudo, u, u_micro of unlabelled training pairs."""
    return ",\n".join([
        base(w, rate), score_cte(), "un as (select pair_id, y, p_yes, (p_yes > 0.5)::int as pseudo from scored where split = 'train' and pair_id not in (select pair_id from lab))",
        score_cte("m", "pas", KEEP, "pass"),
        "uns as (select un.pair_id, un.y, un.p_yes, un.pseudo, round(stddev_pop(pas.p_yes), 6) as u, round(round(stddev_pop(pas.p_yes), 6) * 1000000)::bigint as u_micro from un join pas on pas.pair_id = un.pair_id group by all)",
    ])


PRF = """select tp, fp, fn, round(coalesce(tp::double / nullif(tp + fp, 0), 0) * 100, 4) as precision, round(coalesce(tp::double / nullif(tp + fn, 0), 0) * 100, 4) as recall, round(coalesce(2 * tp::double / nullif(2 * tp + fp + fn, 0), 0) * 100, 4) as f1
from (select count(*) filter (y = 1 and pred = 1) as tp, count(*) filter (y = 0 and pred = 1) as fp, count(*) filter (y = 1 and pred = 0) as fn from {0})"""
assert len(WORDS) == 6 and EVIDENCE == 112
