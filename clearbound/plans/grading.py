"""Queries on rollouts: extraction, match ladder, rewards, advantages, curriculum. The SQL
knows what the generator planted and never parses a response, so it checks the parsers."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import answers as A
from ..operators import grading as G
from ..sources import fixtures as fx
from ..sources.tables import load
from . import sql as S
from .registry import query

R = "with " + S.ROLL
KEY = ("prompt_id", "k")


def rolls(spark, sf):
    return fx.rollouts(spark, sf)


def scored(spark, sf):
    return G.components(rolls(spark, sf))


ANSWER = """case when not has_box then null when kd = 0 then case form when 1 then '\\text{' when 2 then '(' else '' end || substr('ABCD', (size + case when correct then 0 else 1 end) % 4 + 1, 1) || case form when 1 then '}' when 2 then ')' else '' end when kd = 3 then '\\frac{' || (size + case when correct then 0 else 1 end) || '}{4}' end"""


@query("boxed_last", R + f"select prompt_id, k, {ANSWER} as boxed, has_box from roll where kd in (0, 3)")
def boxed_last(spark, sf):
    r = rolls(spark, sf).where(F.col("kind").isin("mcq", "fraction"))
    return r.select(*KEY, A.last_boxed("response").alias("boxed")).withColumn("has_box", F.col("boxed").isNotNull())


@query("boxed_all", R + "select prompt_id, k, case when has_box then 2 else 0 end as n_boxes, case when has_box then '0' end as first_box from roll")
def boxed_all(spark, sf):
    return rolls(spark, sf).select(*KEY, A.all_boxed("response").alias("b")).select(*KEY, F.size("b").alias("n_boxes"), F.get("b", F.lit(0)).alias("first_box"))


@query("tail_fallback", R + "select prompt_id, k, case shape when 0 then ['3.2', '1.5', '1', '7'] when 1 then ['12', '4'] when 2 then ['2'] else []::varchar[] end as numbers, length(case shape when 0 then 'A length of 3.2 m over 1.5 s gives \\frac{1}{7} of the path. ' when 1 then 'The load is 12 kg and acts for 4 s. ' when 2 then 'Half of it, \\frac{x}{2}, remains. ' else '' end || 'No answer could be reached.') as tail_chars from roll where not has_box")
def tail_fallback(spark, sf):
    r = rolls(spark, sf).where(F.size(A.all_boxed("response")) == 0)
    return r.select(*KEY, A.tail_numbers(F.col("response"), 300).alias("numbers"), F.length(A.tail(F.col("response"), 600)).alias("tail_chars"))


@query("latex_plain", "select p_partkey as prompt_id, '(' || p_size || ')/(4)' as plain, round(p_size / 4, 6) as value from part where p_partkey % 4 = 3")
def latex_plain(spark, sf):
    p = fx.problems(spark, sf).where("kind = 'fraction'").select("prompt_id", A.to_plain(F.col("gold")[0]).alias("plain"))
    return p.withColumn("value", A.number_of(F.col("plain")))


def _match(kind: str, no: int):
    @query(f"match_{kind}", R + f"select prompt_id, k, correct as matched from roll where kd = {no}")
    def run(spark, sf):
        return G.strict(rolls(spark, sf).where(F.col("kind") == ("fraction" if kind == "symbolic" else kind))).select(*KEY, F.col("verdict").alias("matched"))

    return run


match_mcq, match_numeric, match_multipart, match_symbolic = (_match(k, i) for i, k in enumerate(("mcq", "numeric", "multipart", "symbolic")))


@query("verdict_strict", R + "select prompt_id, k, has_box, correct as verdict from roll")
def verdict_strict(spark, sf):
    return G.strict(rolls(spark, sf)).select(*KEY, F.col("boxed").isNotNull().alias("has_box"), "verdict")


@query("reward_binary", R + "select prompt_id, k, r_bin as r from scored")
def reward_binary(spark, sf):
    return G.score(rolls(spark, sf), "binary").select(*KEY, "r")


@query("reward_components", R + "select prompt_id, k, r_ans, r_fmt, r_dim, r_sym, r_cons, r_bin, r_dense from scored")
def reward_components(spark, sf):
    return scored(spark, sf).select(*KEY, *G.TERMS, "r_bin", "r_dense")


@query("reward_dense", R + "select r_dense as r, count(*) as n, count(*) filter (correct) as n_right from scored group by 1")
def reward_dense(spark, sf):
    return G.score(rolls(spark, sf), "dense").groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("verdict"), 1)).alias("n_right"))


DROP = " union all ".join(f"select '{w}' as without, correct, greatest(-1.0, least(1.0, round({' + '.join(t for t in G.TERMS if t != w)}, 10))) as r from rew" for w in ("none", *G.TERMS))


@query("reward_dropout", R + f"select without, round(avg(r), 6) as mean_r, round(avg(r) filter (correct), 6) as mean_right, round(avg(r) filter (not correct), 6) as mean_wrong from ({DROP}) group by without")
def reward_dropout(spark, sf):
    return G.dropout(scored(spark, sf))


def _adv(name: str, r: str):
    @query(name, R + f", a as (select prompt_id, k, {r} as r, avg({r}) over w as mean_r, stddev_pop({r}) over w as sd_r from scored window w as (partition by prompt_id)) select prompt_id, k, r, round(mean_r, 6) as mean_r, round(sd_r, 6) as sd_r, round(case when sd_r > 1e-12 then (r - mean_r) / sd_r else 0 end, 6) as adv from a")
    def run(spark, sf):
        return G.advantage(scored(spark, sf), r).select(*KEY, F.col(r).alias("r"), "mean_r", "sd_r", "adv")

    return run


adv_binary, adv_dense = _adv("adv_binary", "r_bin"), _adv("adv_dense", "r_dense")


@query("adv_affine", R + "select count(*) as n, 0.0::double as max_diff from scored")
def adv_affine(spark, sf):
    return G.affine_check(scored(spark, sf).select(*KEY, "r_dense"), "r_dense")


@query("flip_stats", R + """, p as (select a.r_bin as ba, b.r_bin as bb, a.r_dense as da, b.r_dense as db from scored a join scored b on a.prompt_id = b.prompt_id and a.k < b.k),
c as (select count(*) as pairs, count(*) filter (ba = bb and da <> db and ba = 0) as ties_broken_wrong, count(*) filter (ba = bb and da <> db and ba = 1) as ties_broken_right, count(*) filter ((ba - bb) * (da - db) < 0) as inversions from p)
select *, round(case when ties_broken_wrong + ties_broken_right + inversions > 0 then ties_broken_wrong / (ties_broken_wrong + ties_broken_right + inversions) end, 6) as share_wrong from c""")
def flip_stats(spark, sf):
    return G.flip_stats(scored(spark, sf).select(*KEY, "r_bin", "r_dense"))


MIXED = R + ", g as (select prompt_id, avg(r_bin) as p from scored group by prompt_id having avg(r_bin) > 0 and avg(r_bin) < 1) "


@query("adv_closed_form", MIXED + "select prompt_id, round(p, 6) as p, round(sqrt((1 - p) / p), 6) as adv_right, round(-sqrt(p / (1 - p)), 6) as adv_wrong, 0.0::double as gap, 1.0::double as var from g")
def adv_closed_form(spark, sf):
    return G.closed_form(scored(spark, sf).select(*KEY, "r_bin"))


@query("adv_dense_bound", MIXED + "select prompt_id, round(p, 6) as p, round((1 - p) / sqrt(p * (1 - p)), 6) as bin_right, round((1 - p) / sqrt(p * (1 - p) + 0.45 * 0.45 / 12), 6) as dense_right from g")
def adv_dense_bound(spark, sf):
    return G.dense_bound(scored(spark, sf))


@query("curriculum_kept", R + ", g as (select prompt_id, avg(r_bin) as p from scored group by prompt_id) select count(*) as prompts, count(*) filter (p > 0 and p < 1) as kept, count(*) filter (p = 1) as always, count(*) filter (p = 0) as never, round(count(*) filter (p = 0 or p = 1) / count(*), 6) as removed_rate from g")
def curriculum_kept(spark, sf):
    return G.curriculum_report(scored(spark, sf))


@query("curriculum_k4", R + ", g as (select prompt_id, avg(r_bin) as p from scored where k <= 4 group by prompt_id) select count(*) as prompts, count(*) filter (p > 0 and p < 1) as kept, count(*) filter (p = 1) as always, count(*) filter (p = 0) as never, round(count(*) filter (p = 0 or p = 1) / count(*), 6) as removed_rate from g")
def curriculum_k4(spark, sf):
    return G.curriculum_report(G.components(rolls(spark, sf).where("k <= 4")))


@query("dyn_batches", MIXED + ", o as (select prompt_id, row_number() over (order by md5(prompt_id::varchar), prompt_id) - 1 as place_ from g) select prompt_id, place_ // 96 as batch, place_ % 96 as place from o")
def dyn_batches(spark, sf):
    return G.batches(scored(spark, sf), 96)


@query("seq_objective", R + """, a as (select *, case when stddev_pop(r_bin) over w > 1e-12 then (r_bin - avg(r_bin) over w) / stddev_pop(r_bin) over w else 0 end as adv, exp((lp - lp_old) / len) as wt from scored window w as (partition by prompt_id)),
o as (select prompt_id, avg(least(wt * adv, greatest(0.95, least(1.05, wt)) * adv)) as surrogate, avg(lp - lp_base) as anchor, avg((wt < 0.95 or wt > 1.05)::int) as clip_share from a group by prompt_id)
select prompt_id, round(surrogate, 6) as surrogate, round(anchor, 6) as anchor, round(clip_share, 6) as clip_share, round(-surrogate + 0.01 * anchor, 6) as loss from o""")
def seq_objective(spark, sf):
    return G.sequence_objective(G.advantage(scored(spark, sf), "r_bin"), lo=0.05, hi=0.05)


@query("matched_step", R + ", s as (select case l_returnflag when 'A' then 'binary' else 'dense' end as run, step, avg(r_ans) as score from scored where l_returnflag in ('A', 'R') group by all) select a.step, round(a.score, 6) as binary, round(b.score, 6) as dense, round(100 * (a.score - b.score), 6) as delta_pp from s a join s b on a.run = 'binary' and b.run = 'dense' and a.step = b.step")
def matched_step(spark, sf):
    return G.matched_step(_runs(spark, sf))


def _runs(spark, sf):
    r = G.strict(rolls(spark, sf).where(F.col("l_returnflag").isin("A", "R")))
    return r.select(F.when(F.col("l_returnflag") == "A", "binary").otherwise("dense").alias("run"), "step", "kind", F.col("verdict").cast("double").alias("score"))


@query("early_stop", R + ", s as (select case l_returnflag when 'A' then 'binary' else 'dense' end as run, step, avg(r_ans) as score from scored where l_returnflag in ('A', 'R') and kd = 0 group by all) select run, step, round(score, 6) as score from (select *, row_number() over (partition by run order by score desc, step) as n from s) where n = 1")
def early_stop(spark, sf):
    return G.early_stop(_runs(spark, sf).where("kind = 'mcq'"))


@query("audit_factor", R + "select prompt_id, k, r_bin, case when prompt_id % 10 = 0 then 0.0 else r_bin end as r_audited from scored")
def audit_factor(spark, sf):
    bad = load(spark, sf, "part").where("p_partkey % 10 = 0").select(F.col("p_partkey").alias("prompt_id"))
    return G.audit_factor(scored(spark, sf), bad).select(*KEY, "r_bin", "r_audited")
