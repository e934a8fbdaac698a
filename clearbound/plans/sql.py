"""Shared parts of the oracle SQL: splits, grams, hashed embeddings, pairs, rollouts."""

NORM = r"trim(regexp_replace(regexp_replace(regexp_replace(lower(text), '\\[a-z]+', ' ', 'g'), '[$(){}\[\],]', ' ', 'g'), '[ \t\n\r\f]+', ' ', 'g'))"
MASKED = r"regexp_extract_all(regexp_replace(" + NORM + r", '[0-9]+', '0', 'g'), '[\p{L}\p{N}_]+')"
TOKENS = rf"regexp_extract_all({NORM}, '[\p{{L}}\p{{N}}_]+')"
GRAMS = "case when len(t) >= {k} then list_distinct(list_transform(range(1, len(t) - {k} + 2), lambda i: array_to_string(t[i : i + {k} - 1], ' '))) else [] end"

SPLIT = """
md as (select *, ('0x' || substr(md5(doc_id::varchar), 1, 8))::bigint % 5 = 0 as is_eval from documents),
tr as (select doc_id as id, text, lang, source, 'P' || (substr(source, 4)::int // 4)::varchar as pool from md where not is_eval),
ev as (select doc_id as id, text, lang, source from md where is_eval),
members as (select id, lang as eval from ev union all select id, 'all' from ev)
"""


#: As SPLIT, with the benchmark's passages among the evals.
SPLIT6 = SPLIT.replace("from md where is_eval),", "from md where is_eval union all select -1 - item_id, text, 'benchmark', null from benchmark),").replace("select id, 'all' from ev", "select id, 'all' from ev where id >= 0")


def grams(name: str, source: str, k: int = 5, key: str = "id") -> str:
    """name(key, g, n): distinct k-grams and their number."""
    return f"""
{name}_t as (select {key}, {TOKENS} as t from {source}),
{name}_l as (select {key}, {GRAMS.format(k=k)} as l from {name}_t),
{name} as (select {key}, unnest(l) as g, len(l) as n from {name}_l)"""


LEX = SPLIT + "," + grams("tg", "tr") + "," + grams("eg", "ev") + """,
lex as (select t.id as t_id, e.id as e_id, count(*) as inter, count(*) / (any_value(t.n) + any_value(e.n) - count(*)) as jaccard from tg t join eg e using (g) group by all),
lexbest as (select id as t_id, coalesce(max(jaccard), 0) as j_max, arg_max(e_id, jaccard - e_id * 1e-13) as best_lex from tr left join lex on lex.t_id = tr.id group by all)
"""


def e1(name: str, source: str, key: str = "id") -> str:
    return f"""
{name}_x as (select {key} as id, {NORM} as x from {source}),
{name}_g as (select id, g, count(*) as tf from (select id, unnest(list_transform(range(1, length(x) - 2), lambda i: substr(x, i, 4))) as g from {name}_x where length(x) >= 4) group by all),
{name}_w as (select id, ('0x' || substr(md5(g), 1, 8))::bigint % 1024 as b, sum((1 - 2 * (('0x' || substr(md5(g), 9, 1))::int & 1)) * (1 + ln(tf))) as w from {name}_g group by all),
{name} as (select id, b, w / sqrt(sum(w * w) over (partition by id)) as w from {name}_w where w <> 0)"""


def e2(name: str, source: str) -> str:
    """Needs ``idf`` (slot, idf) and ``nodf``."""
    return f"""
{name}_g as (select id, g, count(*) as tf from (select id, unnest({TOKENS}) as g from {source}) group by all),
{name}_h as (select id, ('0x' || substr(md5(g), 1, 8))::bigint as h, (1 - 2 * (('0x' || substr(md5(g), 9, 1))::int & 1)) * (1 + ln(tf)) as w from {name}_g),
{name}_w as (select id, h % 1024 as b, sum(w * idf) as w from {name}_h join idf on idf.slot = h % 262144 group by all),
{name} as (select id, b, w / sqrt(sum(w * w) over (partition by id)) as w from {name}_w where w <> 0)"""


IDF = f"""
slots as (select distinct doc_id, ('0x' || substr(md5(g), 1, 8))::bigint % 262144 as slot from (select doc_id, unnest({TOKENS}) as g from documents)),
idf as (select slot, ln((1 + (select count(*) from documents)) / (1 + count(*))) + 1 as idf from slots group by slot)"""

COS1 = "," + e1("t1", "tr") + "," + e1("v1", "ev") + """,
cos1 as (select t1.id as t_id, v1.id as e_id, sum(t1.w * v1.w) as cosine from t1 join v1 using (b) group by all)
"""
BEST1 = """,
best1 as (
  select tr.id as t_id, coalesce(max(cosine), 0) as c_max from tr left join cos1 on cos1.t_id = tr.id group by all
), semarg as (
  select b.t_id, min(c.e_id) as best_sem from best1 b join (select t.id as t_id, e.id as e_id, coalesce(c.cosine, 0) as cosine from tr t cross join ev e left join cos1 c on c.t_id = t.id and c.e_id = e.id) c on c.t_id = b.t_id and c.cosine >= b.c_max - 1e-9 group by all
)
"""
COS2 = "," + IDF + "," + e2("t2", "tr") + "," + e2("v2", "ev") + """,
cos2 as (select t2.id as t_id, v2.id as e_id, sum(t2.w * v2.w) as cosine from t2 join v2 using (b) group by all),
best2 as (select tr.id as t_id, coalesce(max(cosine), 0) as c_max from tr left join cos2 on cos2.t_id = tr.id group by all)
"""

#: Pairs that either stage flags, with the rule judge's label.
PAIRS = LEX + COS1 + f""",
pr as (
  select coalesce(l.t_id, c.t_id) as t_id, coalesce(l.e_id, c.e_id) as e_id, l.jaccard, c.cosine, l.t_id is not null as stage1, c.t_id is not null as stage2
  from (select * from lex where jaccard >= 0.4 - 1e-9) l full join (select * from cos1 where cosine >= 0.85 - 1e-9) c on l.t_id = c.t_id and l.e_id = c.e_id
),
mt as (select id, t, {GRAMS.format(k=3)} as l from (select id, {MASKED} as t from tr where id in (select t_id from pr))),
me as (select id, t, {GRAMS.format(k=3)} as l from (select id, {MASKED} as t from ev where id in (select e_id from pr))),
vd as (
  select pr.*, case when least(len(mt.l), len(me.l)) > 0 then len(list_intersect(mt.l, me.l)) / least(len(mt.l), len(me.l)) else 0 end as contained,
    case when greatest(len(mt.t), len(me.t)) > 0 then least(len(mt.t), len(me.t)) / greatest(len(mt.t), len(me.t)) else 1 end as length_ratio
  from pr join mt on mt.id = pr.t_id join me on me.id = pr.e_id
),
verdict as (select *, case when contained >= 0.5 - 1e-9 and length_ratio >= 0.5 - 1e-9 then 'close_dup' else 'topic_neighbor' end as label from vd)
"""

ROLL = """
prob as (select p_partkey as prompt_id, p_partkey % 4 as kd, ['mcq', 'numeric', 'multipart', 'fraction'][p_partkey % 4 + 1] as kind, (p_size - 1) // 5 + 1 as difficulty, p_type as concept, p_brand as source, round(p_retailprice, 2) as price, p_size as size from part),
ln as (select *, row_number() over (partition by l_partkey order by l_orderkey, l_linenumber, l_suppkey, l_extendedprice, l_shipdate) as k from lineitem),
r0 as (
  select prompt_id, k, kd, kind, difficulty, concept, source, price, size, l_suppkey as model, case l_suppkey % 3 when 0 then 42 when 1 then 17 else 23 end as seed, l_linestatus as arm, l_linenumber % 4 as shape,
    (7 * l_orderkey + 13 * l_linenumber + 3 * l_suppkey) % 100 + case when l_linestatus = 'F' then 8 else 0 end as h, 45 + (37 * l_suppkey) % 50 - 5 * difficulty as skill,
    l_orderkey, l_orderkey % 5 as form, l_linenumber, l_returnflag, 10 * (1 + floor(l_quantity / 9))::int as step, -l_quantity / 10 as lp, -l_quantity / 10 + l_discount - 0.05 as lp_old, -l_quantity / 10 + l_tax - 0.04 as lp_base, l_linenumber + 1 as len
  from ln join prob on l_partkey = prompt_id where k <= 16
),
roll as (
  select *, h < skill as correct, h < skill or h % 4 <> 3 as has_box, h < skill or (h % 4 = 0 and kd in (1, 2)) as ok2, h < skill or (h % 4 in (0, 1) and kd in (1, 2)) as ok5,
    case when h < skill then 1.0 when kd = 2 and h % 4 = 2 then 0.5 else 0.0 end as partial1,
    case when h < skill or (h % 4 = 0 and kd in (1, 2)) then 1.0 when kd = 2 and h % 4 = 2 then 0.5 else 0.0 end as partial2
  from r0
),
rew as (
  select *, correct::int::double as r_ans, case when has_box then 0.1 else 0.0 end as r_fmt, case when shape in (0, 1) or (kd = 1 and has_box and form = 1) then 0.15 else 0.0 end as r_dim,
    case when shape in (0, 2) or (kd = 3 and has_box) or (kd = 1 and has_box and form = 4) then 0.2 else 0.0 end as r_sym, case when kd = 1 and not correct and h % 4 = 2 then -0.25 else 0.0 end as r_cons
  from roll
),
scored as (select *, r_ans as r_bin, greatest(-1.0, least(1.0, round(r_ans + r_fmt + r_dim + r_sym + r_cons, 10))) as r_dense from rew)
"""


def half_tail(b: str, c: str) -> str:
    """Sum of binomial ratios to min(b, c) over 2^n, or the normal tail beyond n = 1000."""
    n, m = f"({b} + {c})", f"least({b}, {c})"
    z = f"((least({b}, {c}) + 0.5 - {n} / 2.0) / sqrt({n} / 4.0))"
    t = f"(1 / (1 + 0.3275911 * (abs{z} / sqrt(2.0))))"
    erf = f"(1 - (((((1.061405429 * {t} - 1.453152027) * {t}) + 1.421413741) * {t} - 0.284496736) * {t} + 0.254829592) * {t} * exp(-(abs{z} / sqrt(2.0)) * (abs{z} / sqrt(2.0))))"
    exact = f"(1 + coalesce(list_sum(list_transform(range(1, ({m}) + 1), lambda i: exp(lgamma({n} + 1) - lgamma(i + 1) - lgamma({n} - i + 1)))), 0)) * pow(2.0, -{n})"
    return f"case when {n} = 0 then 1.0 when {n} <= 1000 then {exact} when {z} >= 0 then 0.5 * (1 + {erf}) else 0.5 * (1 - {erf}) end"


