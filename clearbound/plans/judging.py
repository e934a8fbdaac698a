"""Queries on verdicts: strict and liberal scores, policies, judge comparisons, statistics."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import answers as A
from ..operators import grading as G
from ..operators import judging as J
from ..operators import stats as T
from ..sources import fixtures as fx
from ..sources.tables import load, share
from . import sql as S
from .registry import query

R = "with " + S.ROLL
KEYS = ["prompt_id", "k"]
KINDS = ["mcq", "numeric", "multipart", "fraction"]


def boxed(spark, sf):
    return G.extracted(fx.rollouts(spark, sf))


def verdicts(spark, sf):
    """Each rollout with the strict verdict and two liberal ones (2 % and 5 %)."""
    b = boxed(spark, sf)
    return b.select("*", G.agrees(F.col("boxed"), 0.01).alias("v1"), G.agrees(F.col("boxed"), 0.02).alias("v2"), G.agrees(F.col("boxed"), 0.05).alias("v5"))


acc = lambda c: F.avg(F.col(c).cast("int"))


@query("strict_accuracy", R + "select model, count(*) as n, round(avg(correct::int), 6) as acc from roll group by model")
def strict_accuracy(spark, sf):
    return verdicts(spark, sf).groupBy("model").agg(F.count(F.lit(1)).alias("n"), acc("v1").alias("acc"))


@query("liberal_problem", R + "select model, count(*) as n, round(avg(ok2::int), 6) as acc from roll group by model")
def liberal_problem(spark, sf):
    return J.liberal_problem(boxed(spark, sf)).groupBy("model").agg(F.count(F.lit(1)).alias("n"), acc("judged").alias("acc"))


@query("liberal_subpart_and", R + "select model, count(*) as n, round(avg(correct::int), 6) as acc_and, round(avg(partial1), 6) as acc_partial, round(avg(partial1) - avg(correct::int), 6) as gap from roll where kd <> 3 group by model")
def liberal_subpart_and(spark, sf):
    p = J.all_parts(J.subparts(boxed(spark, sf).where("kind <> 'fraction'")), [*KEYS, "model"])
    return p.groupBy("model").agg(F.count(F.lit(1)).alias("n"), acc("judged").alias("acc_and"), F.avg("partial").alias("acc_partial")).withColumn("gap", F.col("acc_partial") - F.col("acc_and"))


@query("liberal_cached", R + "select model, count(*) as n, round(avg(ok2::int), 6) as acc, round(avg(case when kd = 2 and not has_box and ((shape = 0 and size in (1, 7)) or (shape = 1 and size in (4, 12)) or (shape = 2 and size = 2)) then 0.5 else partial2 end), 6) as acc_partial from roll where kd in (1, 2) group by model")
def liberal_cached(spark, sf):
    b = boxed(spark, sf).where(F.col("kind").isin("numeric", "multipart"))
    cache = fx.problems(spark, sf).select("prompt_id", F.transform("gold", lambda g: F.trim(g)).alias("clean"))
    strict = J.subparts(b, 0.01).select(*KEYS, "part", "part_ok")
    out = J.liberal_cached(b, cache, strict, KEYS).join(b.select(*KEYS, "model"), KEYS)
    return out.groupBy("model").agg(F.count(F.lit(1)).alias("n"), acc("judged").alias("acc"), F.avg("partial").alias("acc_partial"))


@query("partial_credit_gap", R + "select kind, round(avg(correct::int), 6) as acc_and, round(avg(partial1), 6) as acc_partial, round(100 * (avg(partial1) - avg(correct::int)), 6) as gap_pp from roll group by kind")
def partial_credit_gap(spark, sf):
    p = J.all_parts(J.subparts(boxed(spark, sf)), [*KEYS, "kind"])
    return p.groupBy("kind").agg(acc("judged").alias("acc_and"), F.avg("partial").alias("acc_partial")).withColumn("gap_pp", 100 * (F.col("acc_partial") - F.col("acc_and")))


@query("strict_liberal_gap", R + "select model, round(avg(correct::int), 6) as strict, round(avg(ok2::int), 6) as liberal, round(100 * (avg(ok2::int) - avg(correct::int)), 6) as gap_pp from roll group by model")
def strict_liberal_gap(spark, sf):
    return verdicts(spark, sf).groupBy("model").agg(acc("v1").alias("strict"), acc("v2").alias("liberal")).withColumn("gap_pp", 100 * (F.col("liberal") - F.col("strict")))


STATE = "case event_type when 'purchase' then 'yes' when 'view' then 'no' when 'click' then 'no' when 'error' then 'error' else 'unjudgeable' end"


def event_states(spark, sf):
    e = F.col("event_type")
    state = F.when(e == "purchase", "yes").when(e.isin("view", "click"), "no").when(e == "error", "error").otherwise("unjudgeable")
    return load(spark, sf, "events").withColumn("state", state)


@query("verdict_parse", "select case event_type when 'purchase' then 'yes' when 'view' then 'no' when 'error' then 'error' else 'unparseable' end as state, count(*) as n from events group by 1")
def verdict_parse(spark, sf):
    said = F.create_map(*(F.lit(x) for x in ("purchase", "YES.", "view", " no", "click", "Yes or no?", "signup", "maybe")))
    return load(spark, sf, "events").groupBy(J.parse_verdict(F.try_element_at(said, F.col("event_type"))).alias("state")).agg(F.count(F.lit(1)).alias("n"))


@query("policy_bounds", f"with e as (select user_id as model, {STATE} as s from events) select model, count(*) as n, count(*) filter (s in ('yes', 'no')) as judged, count(*) filter (s = 'yes') as yes, count(*) filter (s = 'error') as errors, count(*) filter (s = 'unparseable') as unparseable, count(*) filter (s = 'unjudgeable') as unjudgeable, round(count(*) filter (s = 'yes') / count(*), 6) as low, round(case when count(*) filter (s in ('yes', 'no')) > 0 then count(*) filter (s = 'yes') / count(*) filter (s in ('yes', 'no')) end, 6) as high from e group by model")
def policy_bounds(spark, sf):
    return J.policy_bounds(event_states(spark, sf).withColumnRenamed("user_id", "model"), ["model"])


@query("policy_variants", f"with e as (select {STATE} as s from events), c as (select count(*) as n, count(*) filter (s = 'yes') as y, count(*) filter (s = 'error') as er, count(*) filter (s = 'unjudgeable') as un from e) select 'all_wrong' as policy, n as denominator, round(y / n, 6) as score from c union all select 'drop_errors', n - er, round(y / (n - er), 6) from c union all select 'drop_unjudgeable', n - un, round(y / (n - un), 6) from c union all select 'judged_only', n - er - un, round(y / (n - er - un), 6) from c")
def policy_variants(spark, sf):
    e = event_states(spark, sf)
    s = F.col("state")
    rows = {"all_wrong": J.apply_policy(s), "drop_errors": J.apply_policy(s, error="drop"), "drop_unjudgeable": J.apply_policy(s, unjudgeable="drop"), "judged_only": J.apply_policy(s, error="drop", unjudgeable="drop")}
    long = e.select(F.explode(F.array(*(F.struct(F.lit(k).alias("policy"), v.alias("v")) for k, v in rows.items()))).alias("r"))
    return long.groupBy("r.policy").agg(F.count("r.v").alias("denominator"), F.avg("r.v").alias("score"))


@query("dedup_score_range", R + """, g as (select seed, prompt_id, model, count(*) as n, sum(correct::int) as s, arg_min(correct::int, k) as first, arg_max(correct::int, k) as last, max(correct::int) as any_, min(correct::int) as every from roll group by all)
select seed, sum(n)::bigint as rows, count(*) as ids, round(sum(s) / sum(n), 6) as score_none, round(avg(first), 6) as score_first, round(avg(last), 6) as score_last, round(avg(any_), 6) as score_any, round(avg(every), 6) as score_every from g group by seed""")
def dedup_score_range(spark, sf):
    return J.dedup_range(verdicts(spark, sf).select("seed", "prompt_id", "model", "k", "v1"), ["prompt_id", "model"], ["k"], "v1", ["seed"])


SWAP = R + """, s as (select kind, model % 10 as model, ok5 as a, ok2 as b from roll),
c as (select kind, model, count(*) as n, avg((a = b)::int) as po, avg(a::int) as ra, avg(b::int) as rb from s group by all)
select kind as column_, model, n, round(po, 6) as agree, round(case when ra * rb + (1 - ra) * (1 - rb) = 1 then 1 else (po - ra * rb - (1 - ra) * (1 - rb)) / (1 - ra * rb - (1 - ra) * (1 - rb)) end, 6) as kappa, round(ra, 6) as acc_a, round(rb, 6) as acc_b, round(100 * (ra - rb), 6) as delta from c"""


@query("judge_swap", SWAP)
def judge_swap(spark, sf):
    v = verdicts(spark, sf).select(F.col("kind").alias("column_"), (F.col("model") % 10).alias("model"), "v5", "v2")
    by = ["column_", "model"]
    rates = v.groupBy(*by).agg(acc("v5").alias("acc_a"), acc("v2").alias("acc_b")).withColumn("delta", 100 * (F.col("acc_a") - F.col("acc_b")))
    return T.kappa(v, "v5", "v2", by).join(rates, by)


MODELS = R + ", m as (select model % 10 as model, avg(ok5::int) as a, avg(ok2::int) as b from roll group by 1) "


def model_scores(spark, sf):
    return verdicts(spark, sf).groupBy((F.col("model") % 10).alias("model")).agg(acc("v5").alias("a"), acc("v2").alias("b"))


@query("rank_reversal", MODELS + "select x.model as model_1, y.model as model_2, sign(round(x.a - y.a, 9))::int as sign_a, sign(round(x.b - y.b, 9))::int as sign_b, sign(round(x.a - y.a, 9)) * sign(round(x.b - y.b, 9)) < 0 as reversed from m x join m y on x.model < y.model")
def rank_reversal(spark, sf):
    return J.rank_reversals(model_scores(spark, sf), "a", "b")


@query("lift_sign", MODELS + "select m.model, round(m.a - z.a, 6) as lift_a, round(m.b - z.b, 6) as lift_b, sign(round(m.a - z.a, 9)) = sign(round(m.b - z.b, 9)) as same_sign from m, (select * from m where model = 0) z")
def lift_sign(spark, sf):
    return J.lift_signs(model_scores(spark, sf), F.col("model") == 0, "a", "b")


@query("chunk_breakdown", R + ", c as (select ok2, ntile(5) over (partition by n_nationkey order by md5(key), key) as chunk from (select ok2, prompt_id * 100 + k as key_, (prompt_id * 100 + k)::varchar as key, s_nationkey as n_nationkey from roll join supplier on s_suppkey = model)) select chunk, count(*) as n, count(*) filter (ok2) as yes, round(count(*) filter (ok2) / count(*), 6) as rate from c group by chunk")
def chunk_breakdown(spark, sf):
    s = load(spark, sf, "supplier").select(F.col("s_suppkey").alias("model"), "s_nationkey")
    rows = verdicts(spark, sf).join(F.broadcast(s), "model").select("v2", "s_nationkey", (F.col("prompt_id") * 100 + F.col("k")).cast("string").alias("key"))
    c = J.chunks(rows, "s_nationkey", F.col("key"))
    return c.groupBy("chunk").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("v2"), 1)).alias("yes"), acc("v2").alias("rate"))


@query("heldout_sample", "select doc_id, source from (select *, row_number() over (partition by source order by md5(doc_id::varchar), doc_id) as n from documents) where n <= 7")
def heldout_sample(spark, sf):
    return J.stratified(load(spark, sf, "documents").select("doc_id", "source"), "source", "doc_id", 7)


@query("acc_by_difficulty", R + "select difficulty, count(*) as n, count(*) filter (correct) as right_, round(avg(correct::int), 6) as acc, avg(correct::int) = 0 as floor_ from roll group by difficulty")
def acc_by_difficulty(spark, sf):
    return verdicts(spark, sf).groupBy("difficulty").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("v1"), 1)).alias("right_"), acc("v1").alias("acc")).withColumn("floor_", F.col("acc") == 0)


@query("acc_cube", R + "select concept, kind, grouping_id(concept, kind)::bigint as level, count(*) as n, round(avg(correct::int), 6) as acc from roll group by cube (concept, kind)")
def acc_cube(spark, sf):
    return verdicts(spark, sf).cube("concept", "kind").agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"), acc("v1").alias("acc"))


@query("format_gradient", R + ", a as (select model % 10 as model, kind, avg(correct::int) as acc from roll group by all), l as (select *, acc - lag(acc) over (partition by model order by kind) as step from a) select model, round(max(acc) - min(acc), 6) as spread, round(max(abs(step)), 6) as largest_step from l group by model")
def format_gradient(spark, sf):
    a = verdicts(spark, sf).groupBy((F.col("model") % 10).alias("model"), "kind").agg(acc("v1").alias("acc"))
    step = F.col("acc") - F.lag("acc").over(Window.partitionBy("model").orderBy("kind"))
    return a.withColumn("step", step).groupBy("model").agg((F.max("acc") - F.min("acc")).alias("spread"), F.max(F.abs("step")).alias("largest_step"))


WIDE = R + ", w as (select model % 10 as model, " + ", ".join(f"avg(ok2::int) filter (kind = '{k}') as {k}" for k in KINDS) + " from roll group by 1) "


@query("leaderboard", WIDE + "select w.model, " + ", ".join(f"round(w.{k}, 6) as {k}, round(w.{k} - z.{k}, 6) as delta_{k}, dense_rank() over (order by w.{k} desc nulls last)::int as rank_{k}" for k in KINDS) + " from w, (select * from w where model = 0) z")
def leaderboard(spark, sf):
    a = verdicts(spark, sf).groupBy((F.col("model") % 10).alias("model"), "kind").agg(acc("v2").alias("acc"))
    return J.leaderboard(a, 0, KINDS)


@query("seed_summary", R + ", s as (select kind, seed, 100 * avg(ok2::int) as score from roll group by all) select kind as column_, count(*) as n_seeds, round(avg(score), 6) as mean, round(stddev_samp(score), 6) as sd_sample, round(avg(score) - min(score) filter (seed = 42), 6) as lift from s group by kind")
def seed_summary(spark, sf):
    s = verdicts(spark, sf).groupBy("kind", "seed").agg((100 * acc("v2")).alias("score"))
    return s.groupBy(F.col("kind").alias("column_")).agg(F.count(F.lit(1)).alias("n_seeds"), F.avg("score").alias("mean"), F.stddev_samp("score").alias("sd_sample"), (F.avg("score") - F.min(F.when(F.col("seed") == 42, F.col("score")))).alias("lift"))


@query("flips", R + ", f as (select prompt_id, bool_or(correct) filter (k = 1) as a, bool_or(correct) filter (k = 2) as b from roll where k <= 2 group by prompt_id) select prompt_id from f where not a and b order by md5(prompt_id::varchar), prompt_id limit 30")
def flips(spark, sf):
    f = G.strict(fx.rollouts(spark, sf).where("k <= 2")).groupBy("prompt_id").agg(F.bool_or(F.when(F.col("k") == 1, F.col("verdict"))).alias("a"), F.bool_or(F.when(F.col("k") == 2, F.col("verdict"))).alias("b"))
    return f.where("not a and b").orderBy(F.md5(F.col("prompt_id").cast("string")), "prompt_id").limit(30).select("prompt_id")


@query("commit_rate", R + "select model, count(*) filter (has_box) as boxed, count(*) as n, round(avg(has_box::int), 6) as rate from roll group by model")
def commit_rate(spark, sf):
    return boxed(spark, sf).groupBy("model").agg(F.count("boxed").alias("boxed"), F.count(F.lit(1)).alias("n"), F.avg(F.col("boxed").isNotNull().cast("int")).alias("rate"))


@query("failure_kinds", R + "select case when not has_box then 'no_box' when kd = 0 then 'wrong_choice' when kd = 3 then 'wrong_expression' when h % 4 in (0, 1) then 'within_5' else 'magnitude' end as failure, count(*) as n from roll where not correct group by 1")
def failure_kinds(spark, sf):
    v = G.strict(fx.rollouts(spark, sf)).where("not verdict")
    return v.groupBy(J.failure_kind(F.col("boxed"), F.col("gold"), F.col("kind")).alias("failure")).agg(F.count(F.lit(1)).alias("n"))


@query("rederive_cells", R + "select kind, model, round(avg(correct::int), 6) as acc, true as same from roll group by all")
def rederive_cells(spark, sf):
    v = G.strict(fx.rollouts(spark, sf)).select(*KEYS, "kind", "model", "verdict")
    cells = v.groupBy("kind", "model").agg(acc("verdict").alias("acc"))
    log = v.select(F.to_json(F.struct("kind", "model", F.when(F.col("verdict"), "YES").otherwise("NO").alias("said"))).alias("line"))
    back = log.select(F.from_json("line", "kind string, model long, said string").alias("r")).select("r.*")
    again = back.groupBy("kind", "model").agg(F.avg((J.parse_verdict(F.col("said")) == "yes").cast("int")).alias("again"))
    return cells.join(again, ["kind", "model"]).select("kind", "model", "acc", (F.abs(F.col("acc") - F.col("again")) < 1e-12).alias("same"))


@query("mcq_floor", "with g as (select p_partkey, substr('ABCD', p_size % 4 + 1, 1) as gold, substr('ABCD', (('0x' || substr(md5(p_partkey::varchar), 1, 8))::bigint % 4 + 1)::int, 1) as guess from part where p_partkey % 4 = 0) select count(*) as n, count(*) filter (gold = guess) as hits, round(avg((gold = guess)::int), 6) as rate from g")
def mcq_floor(spark, sf):
    from ..functions.text import md5_int

    p = fx.problems(spark, sf).where("kind = 'mcq'").withColumn("guess", F.substring(F.lit("ABCD"), (md5_int(F.col("prompt_id").cast("string")) % 4 + 1).cast("int"), F.lit(1)))
    hit = A.match_letter(F.col("guess"), F.col("gold")[0])
    return p.agg(F.count(F.lit(1)).alias("n"), F.count(F.when(hit, 1)).alias("hits"), F.avg(hit.cast("int")).alias("rate"))


# -- statistics


@query("judge_agreement", R + "select kind, count(*) as n, round(avg((ok5 = ok2)::int), 6) as agree from roll group by kind")
def judge_agreement(spark, sf):
    v = verdicts(spark, sf)
    return v.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("v5") == F.col("v2")).cast("int")).alias("agree"))




def kappa_sql(source: str, a: str, b: str) -> str:
    return f"""
, ka as (select {a}::varchar as a, {b}::varchar as b from {source}), kn as (select count(*) as n, avg((a = b)::int) as po from ka),
kp as (select coalesce(sum(x.p * y.p), 0) as pe from (select a as c, count(*) / (select n from kn) as p from ka group by 1) x join (select b as c, count(*) / (select n from kn) as p from ka group by 1) y using (c))
select n, round(po, 6) as agree, round(case when pe = 1 then 1 else (po - pe) / (1 - pe) end, 6) as kappa from kn, kp"""


@query("kappa_binary", R + kappa_sql("roll", "correct", "ok2"))
def kappa_binary(spark, sf):
    return T.kappa(verdicts(spark, sf), "v1", "v2")


LENGTHS = rf"""with d as (select case when n_chars < 300 then 'S' when n_chars < 2000 then 'M' else 'L' end as a, case when len(t) < 50 then 'S' when len(t) < 330 then 'M' else 'L' end as b from (select n_chars, {S.TOKENS} as t from documents))"""


@query("kappa_multi", LENGTHS + kappa_sql("d", "a", "b"))
def kappa_multi(spark, sf):
    return T.kappa(length_classes(spark, sf), "a", "b")


def length_classes(spark, sf):
    from ..functions import text as X

    n = F.size(X.tokens(X.normalize(F.col("text"))))
    rows = load(spark, sf, "documents").select("n_chars", n.alias("n"))
    return rows.select(F.when(F.col("n_chars") < 300, "S").when(F.col("n_chars") < 2000, "M").otherwise("L").alias("a"), F.when(F.col("n") < 50, "S").when(F.col("n") < 330, "M").otherwise("L").alias("b"))


@query("human_kappa", rf"""with d as (select l.quality as a, (length(regexp_replace(text, '[^\p{{L}}]', '', 'g')) / greatest(length(text), 1) >= 0.7)::int as b from labels l join documents using (doc_id))""" + kappa_sql("d", "a", "b"))
def human_kappa(spark, sf):
    d = load(spark, sf, "labels").join(load(spark, sf, "documents"), "doc_id")
    letters = F.length(F.regexp_replace("text", r"[^\p{L}]", ""))
    return T.kappa(d.select(F.col("quality").alias("a"), (letters / F.greatest(F.length("text"), F.lit(1)) >= 0.7).cast("int").alias("b")), "a", "b")


@query("mcnemar", R + f", c as (select kind, count(*) as n_pairs, count(*) filter (correct and not ok2) as only_a, count(*) filter (ok2 and not correct) as only_b from roll group by kind) select kind, n_pairs, only_a, only_b, round(least(1.0, 2 * ({S.half_tail('only_a', 'only_b')})), 6) as p from c")
def mcnemar(spark, sf):
    b = G.extracted(fx.rollouts(spark, sf))
    return T.mcnemar(b.select("kind", G.agrees(F.col("boxed"), 0.01).alias("v1"), G.agrees(F.col("boxed"), 0.02).alias("v2")), "v1", "v2", ["kind"])


PAIRED = R + """, f as (select prompt_id, arm, arg_min(correct, k) as ok from roll group by all), p as (select o.prompt_id, o.ok as a, t.ok as b from f o join f t on o.prompt_id = t.prompt_id and o.arm = 'O' and t.arm = 'F')"""


def language_pairs(spark, sf):
    v = G.strict(fx.rollouts(spark, sf)).groupBy("prompt_id", "arm").agg(F.min(F.struct("k", "verdict")).getField("verdict").alias("ok"))
    return v.groupBy("prompt_id").agg(F.bool_or(F.when(F.col("arm") == "O", F.col("ok"))).alias("a"), F.bool_or(F.when(F.col("arm") == "F", F.col("ok"))).alias("b")).where("a is not null and b is not null")


def paired_sql(by: str = "") -> str:
    g = f"group by {by}" if by else ""
    c = f"{by}, " if by else ""
    return f", c as (select {c}count(*) as n_pairs, count(*) filter (a and not b) as only_a, count(*) filter (b and not a) as only_b, 100 * (avg(a::int) - avg(b::int)) as delta_pp from p {g}) select {c}n_pairs, only_a, only_b, round(delta_pp, 6) as delta_pp, round(least(1.0, {S.half_tail('only_a', 'only_b')}), 6) as p_one, round(least(1.0, 2 * ({S.half_tail('only_a', 'only_b')})), 6) as p_two from c"


@query("paired_language_delta", PAIRED + paired_sql())
def paired_language_delta(spark, sf):
    return T.paired(language_pairs(spark, sf), "a", "b")


@query("sign_test", PAIRED.replace("select o.prompt_id, o.ok as a", "select o.prompt_id % 10 as g, o.ok as a") + paired_sql("g"))
def sign_test(spark, sf):
    return T.paired(language_pairs(spark, sf).withColumn("g", F.col("prompt_id") % 10), "a", "b", ["g"])


@query("rate_ci", R + ", c as (select model, count(*) as n, sum(correct::int) as x from roll group by model), w as (select *, x / n as p, 1.959963984540054 as z from c) select model, n, round(p, 6) as rate, round((p + z * z / (2 * n)) / (1 + z * z / n) - z * sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n), 6) as lo, round((p + z * z / (2 * n)) / (1 + z * z / n) + z * sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / (1 + z * z / n), 6) as hi from w")
def rate_ci(spark, sf):
    c = G.strict(fx.rollouts(spark, sf)).groupBy("model").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("verdict").cast("int")).alias("x"))
    lo, hi = T.wilson(F.col("x"), F.col("n"))
    return c.select("model", "n", share(F.col("x"), F.col("n")).alias("rate"), lo.alias("lo"), hi.alias("hi"))


@query("cross_judge_sample", R + ", s as (select ok2, ok5, row_number() over (order by md5((prompt_id * 100 + k)::varchar), prompt_id, k) as n from roll), t as (select * from s where n <= 50) select count(*) filter (ok2 and ok5) as both_yes, count(*) filter (not ok2 and not ok5) as both_no, count(*) filter (ok5 and not ok2) as only_a, count(*) filter (ok2 and not ok5) as only_b from t")
def cross_judge_sample(spark, sf):
    r = fx.rollouts(spark, sf).orderBy(F.md5((F.col("prompt_id") * 100 + F.col("k")).cast("string")), "prompt_id", "k").limit(50)
    v = G.extracted(r).select(G.agrees(F.col("boxed"), 0.05).alias("a"), G.agrees(F.col("boxed"), 0.02).alias("b"))
    n = lambda c: F.count(F.when(c, 1))
    return v.agg(n(F.col("a") & F.col("b")).alias("both_yes"), n(~F.col("a") & ~F.col("b")).alias("both_no"), n(F.col("a") & ~F.col("b")).alias("only_a"), n(~F.col("a") & F.col("b")).alias("only_b"))


@query("annotation_agreement", rf"""with d as (select (length(regexp_replace(text, '[^\p{{L}}]', '', 'g')) / greatest(length(text), 1) >= 0.7)::int as a, (len({S.TOKENS}) >= 30)::int as b from documents)""" + kappa_sql("d", "a", "b"))
def annotation_agreement(spark, sf):
    """Two heuristic annotators of quality over the same records."""
    from ..functions import text as X

    letters = F.length(F.regexp_replace("text", r"[^\p{L}]", ""))
    a = (letters / F.greatest(F.length("text"), F.lit(1)) >= 0.7).cast("int")
    return T.kappa(load(spark, sf, "documents").select(a.alias("a"), (F.size(X.tokens(X.normalize(F.col("text")))) >= 30).cast("int").alias("b")), "a", "b")


@query("kappa_udaf", R + """, c as (select kind, count(*) as n, avg((ok5 = ok2)::int) as po, avg(ok5::int) as ra, avg(ok2::int) as rb from roll group by kind)
select kind, round(case when ra * rb + (1 - ra) * (1 - rb) = 1 then 1 else (po - ra * rb - (1 - ra) * (1 - rb)) / (1 - ra * rb - (1 - ra) * (1 - rb)) end, 6) as kappa from c""")
def kappa_udaf(spark, sf):
    """The same measure as a grouped pandas aggregate, for groups that fit a task. Verdict
    pairs are counted first, so a group is four rows."""
    cells = verdicts(spark, sf).groupBy("kind", "v5", "v2").agg(F.count(F.lit(1)).alias("c"))
    return cells.groupBy("kind").agg(T.kappa_of_cells("v5", "v2", "c").alias("kappa"))


def profiled(rows):
    """applyInPandas over models: a statistic that needs a model's rows together."""
    import pandas as pd

    def profile(f: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"model": [f["model"].iloc[0]], "n": [len(f)], "median_h": [float(f["h"].median())], "acc": [float(f["verdict"].mean())]})

    v = G.strict(rows).select("model", "h", "verdict")
    return v.groupBy("model").applyInPandas(profile, "model long, n long, median_h double, acc double")


@query("group_profile", R + "select model, count(*) as n, round(median(h), 6) as median_h, round(avg(correct::int), 6) as acc from roll group by model")
def group_profile(spark, sf):
    return profiled(fx.rollouts(spark, sf))
