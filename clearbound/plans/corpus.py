"""Curation queries and the operators around the methods: joins, aggregates, windows,
functions, and the batch twins of the streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import text as X
from ..operators import corpus as C
from ..operators import grading as G
from ..operators import judging as J
from ..sources import fixtures as fx
from ..sources.tables import load
from . import sql as S
from .audit import PAGE_TEXT
from .judging import KINDS, R, acc, event_states, verdicts
from .registry import query

LICENCE = "case when contains(lower(text), 'apache license') then 'apache' when contains(lower(text), 'mit license') then 'mit' when contains(lower(text), 'gnu general public') or contains(lower(text), 'gpl') then 'gpl' when contains(lower(text), 'creative commons') or contains(lower(text), 'cc by') then 'cc-by' when contains(lower(text), 'all rights reserved') then 'reserved' else 'none' end"
docs = lambda spark, sf: load(spark, sf, "documents")
n_rows = lambda name="n": F.count(F.lit(1)).alias(name)


@query("corpus_union", "select family, count(*) as n, count(lang) as with_lang, sum(length(text))::bigint as chars from (select 'documents' as family, text, lang from documents union all select 'benchmark', text, null from benchmark union all select 'conversations', text, null from conversations) group by family")
def corpus_union(spark, sf):
    u = C.unify(docs(spark, sf).select(F.lit("documents").alias("family"), "text", "lang"), load(spark, sf, "benchmark").select(F.lit("benchmark").alias("family"), "text"), load(spark, sf, "conversations").select(F.lit("conversations").alias("family"), "text"))
    return u.groupBy("family").agg(n_rows(), F.count("lang").alias("with_lang"), F.sum(F.length("text")).alias("chars"))


@query("schema_violations", "select v as field, count(*) as n from (select unnest(list_filter([case when difficulty not in (1, 2, 3, 4, 5) then 'difficulty' end, case when length_ not in ('S', 'M', 'L') then 'length' end, case when lang not in ('en', 'de') then 'language' end], lambda x: x is not null)) as v from (select n_chars % 7 as difficulty, case when n_chars < 300 then 'S' when n_chars < 2000 then 'M' when n_chars < 20000 then 'L' else 'XL' end as length_, lang from documents)) group by v")
def schema_violations(spark, sf):
    length = F.when(F.col("n_chars") < 300, "S").when(F.col("n_chars") < 2000, "M").when(F.col("n_chars") < 20000, "L").otherwise("XL")
    rows = docs(spark, sf).select((F.col("n_chars") % 7).alias("difficulty"), length.alias("length"), F.col("lang").alias("language"))
    v = C.violations(rows, {"difficulty": (1, 2, 3, 4, 5), "length": ("S", "M", "L"), "language": ("en", "de")})
    return v.select(F.explode("violations").alias("field")).groupBy("field").agg(n_rows())


@query("license_rollup", f"select coalesce(pool, 'all') as pool, licence, commercial, count(*) as n from (select 'P' || (substr(source, 4)::int // 4)::varchar as pool, {LICENCE} as licence, {LICENCE} in ('apache', 'mit', 'cc-by', 'none') as commercial from documents) group by grouping sets ((pool, licence, commercial), (licence, commercial))")
def license_rollup(spark, sf):
    d = docs(spark, sf).select(fx.pool_of(F.col("source")).alias("pool"), C.licence_of(F.col("text")).alias("licence")).withColumn("commercial", C.commercial_ok(F.col("licence")))
    g = d.groupingSets([["pool", "licence", "commercial"], ["licence", "commercial"]], "pool", "licence", "commercial").agg(n_rows())
    return g.withColumn("pool", F.coalesce("pool", F.lit("all")))


@query("source_counts", "select coalesce(source, 'total') as source, count(*) as n from documents group by rollup (source)")
def source_counts(spark, sf):
    return docs(spark, sf).rollup("source").agg(n_rows()).withColumn("source", F.coalesce("source", F.lit("total")))


@query("bilingual_pairs", "with a as (select l_partkey as p, bool_or(l_linestatus = 'O') as o, bool_or(l_linestatus = 'F') as f from lineitem group by 1) select case when o and f then 'both' when o then 'original_only' else 'translated_only' end as subset, count(*) as n from a group by 1")
def bilingual_pairs(spark, sf):
    a = load(spark, sf, "lineitem").groupBy("l_partkey").agg(F.bool_or(F.col("l_linestatus") == "O").alias("o"), F.bool_or(F.col("l_linestatus") == "F").alias("f"))
    return a.groupBy(F.when(F.col("o") & F.col("f"), "both").when(F.col("o"), "original_only").otherwise("translated_only").alias("subset")).agg(n_rows())


@query("closed_form_pool", "select ['mcq', 'numeric', 'multipart', 'fraction'][p_partkey % 4 + 1] as kind, count(*) as n, p_partkey % 4 <> 2 as closed_form from part group by all")
def closed_form_pool(spark, sf):
    return fx.problems(spark, sf).groupBy("kind").agg(n_rows()).withColumn("closed_form", F.col("kind") != "multipart")


@query("splitter_recovery", r"""with p as (select 'lines' as splitter, doc_id, unnest(regexp_extract_all(text, '[^\n]+')) as t from documents union all select 'sentences', doc_id, unnest(regexp_extract_all(text, '[^.!?\n]+[.!?]?')) from documents),
c as (select splitter, count(*) as pieces, count(distinct doc_id) as docs from p where length(t) >= 20 group by splitter) select splitter, pieces, docs, pieces - (select pieces from c where splitter = 'lines') as gain from c""")
def splitter_recovery(spark, sf):
    return C.splitter_recovery(docs(spark, sf))


@query("page_text", f"select page_id, length({PAGE_TEXT}) as n_chars, md5({PAGE_TEXT}) as digest from pages")
def page_text(spark, sf):
    t = C.page_text(F.col("html"))
    return load(spark, sf, "pages").select("page_id", F.length(t).alias("n_chars"), F.md5(t).alias("digest"))


@query("messages_nested", "select conv_id, count(*) as n_messages, string_agg(role, '>' order by turn) as roles, sum(length(text))::bigint as chars from conversations group by conv_id")
def messages_nested(spark, sf):
    m = C.messages(load(spark, sf, "conversations"))
    return m.select("conv_id", F.size("messages").alias("n_messages"), F.array_join(F.transform("messages", lambda x: x["role"]), ">").alias("roles"), F.aggregate("messages", F.lit(0).cast("long"), lambda s, x: s + F.length(x["content"])).alias("chars"))


@query("difficulty_fields", "select p_size as native_value, (p_size - 1) // 5 + 1 as aggregated, count(*) as n from part group by all")
def difficulty_fields(spark, sf):
    p = fx.problems(spark, sf).select(F.struct(F.lit("1-50").alias("scale"), F.col("size").alias("value")).alias("native_difficulty"), F.col("difficulty").alias("aggregated"))
    return p.groupBy(F.col("native_difficulty.value").alias("native_value"), "aggregated").agg(n_rows())


@query("version_diff", "with o as (select doc_id, text from documents where doc_id % 11 <> 0), n as (select doc_id, case when doc_id % 7 = 0 then text || ' (corrected)' else text end as text from documents where doc_id % 13 <> 0) select coalesce(o.doc_id, n.doc_id) as doc_id, case when o.doc_id is null then 'added' when n.doc_id is null then 'removed' else 'changed' end as change from o full join n on o.doc_id = n.doc_id where o.doc_id is null or n.doc_id is null or o.text <> n.text")
def version_diff(spark, sf):
    d = docs(spark, sf).select("doc_id", "text")
    new = d.where("doc_id % 13 <> 0").withColumn("text", F.when(F.col("doc_id") % 7 == 0, F.concat("text", F.lit(" (corrected)"))).otherwise(F.col("text")))
    return C.version_diff(d.where("doc_id % 11 <> 0"), new, "doc_id")


@query("dataset_card", because="one JSON text, whose layout differs between engines; its values are tested")
def dataset_card(spark, sf):
    return C.card(docs(spark, sf), "documents", "1.0.0", C.licence_of(F.col("text")))


@query("touched_share", "select source, count(*) as n, count(*) filter (doc_id % 31 = 0) as touched, round(count(*) filter (doc_id % 31 = 0) / count(*), 6) as share from documents group by source")
def touched_share(spark, sf):
    t = (F.col("doc_id") % 31 == 0).cast("int")
    return docs(spark, sf).groupBy("source").agg(n_rows(), F.sum(t).alias("touched"), F.avg(t).alias("share"))


@query("digests", "select doc_id, sha256(text) as digest from documents")
def digests(spark, sf):
    return docs(spark, sf).select("doc_id", F.sha2("text", 256).alias("digest"))


# -- scans, filters, joins


@query("scan_documents", "select count(*) as n, count(text) as with_text, min(doc_id) as lo, max(doc_id) as hi, sum(n_chars)::bigint as chars from documents")
def scan_documents(spark, sf):
    return docs(spark, sf).agg(n_rows(), F.count("text").alias("with_text"), F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.sum("n_chars").alias("chars"))


@query("scan_events", "select event_type, count(*) as n, min(ts) as first_ts, max(ts) as last_ts, round(avg(value), 6) as mean_value from events group by event_type")
def scan_events(spark, sf):
    return load(spark, sf, "events").groupBy("event_type").agg(n_rows(), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts"), F.avg("value").alias("mean_value"))


@query("scan_embeddings", "select label, count(*) as n, min(len(embedding)) as dim_lo, max(len(embedding)) as dim_hi from embeddings group by label")
def scan_embeddings(spark, sf):
    return load(spark, sf, "embeddings").groupBy("label").agg(n_rows(), F.min(F.size("embedding")).alias("dim_lo"), F.max(F.size("embedding")).alias("dim_hi"))


@query("scan_pages", "select count(*) as n, count(distinct url) as urls, sum(length(html))::bigint as chars from pages")
def scan_pages(spark, sf):
    return load(spark, sf, "pages").agg(n_rows(), F.countDistinct("url").alias("urls"), F.sum(F.length("html")).alias("chars"))


@query("filter_pushdown", "select doc_id, source, n_chars from documents where lang = 'en' and n_chars between 200 and 5000 and source is distinct from 'src3' and source like 'src1%'")
def filter_pushdown(spark, sf):
    keep = (F.col("lang") == "en") & F.col("n_chars").between(200, 5000) & ~F.col("source").eqNullSafe("src3") & F.col("source").like("src1%")
    return docs(spark, sf).where(keep).select("doc_id", "source", "n_chars")


@query("join_semi", "select doc_id, lang from documents d where exists (select 1 from labels l where l.doc_id = d.doc_id)")
def join_semi(spark, sf):
    return docs(spark, sf).select("doc_id", "lang").join(load(spark, sf, "labels"), "doc_id", "left_semi")


@query("join_anti", "select doc_id, lang from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id)")
def join_anti(spark, sf):
    return docs(spark, sf).select("doc_id", "lang").join(load(spark, sf, "labels"), "doc_id", "left_anti")


@query("join_theta", f"with d as (select doc_id, source, len({S.TOKENS}) as n from documents) select source, count(*) as pairs, count(*) filter (least(a.n, b.n) >= 0.4 * greatest(a.n, b.n)) as fitting from d a join d b using (source) where a.doc_id < b.doc_id group by source")
def join_theta(spark, sf):
    d = docs(spark, sf).select("doc_id", "source", F.size(X.tokens(X.normalize(F.col("text")))).alias("n"))
    a, b = d.alias("a"), d.alias("b")
    j = a.join(b, (F.col("a.source") == F.col("b.source")) & (F.col("a.doc_id") < F.col("b.doc_id")))
    fits = F.least("a.n", "b.n") >= 0.4 * F.greatest("a.n", "b.n")
    return j.groupBy(F.col("a.source").alias("source")).agg(n_rows("pairs"), F.count(F.when(fits, 1)).alias("fitting"))


@query("join_asof", "select e.event_id, p.event_id as last_purchase from (select * from events where event_type = 'error') e asof left join (select * from events where event_type = 'purchase') p on e.user_id = p.user_id and e.ts >= p.ts")
def join_asof(spark, sf):
    """Latest purchase at or before each error: one ordered pass over the union per user."""
    e = load(spark, sf, "events").where(F.col("event_type").isin("error", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_purchase", last).where("event_type = 'error'").select("event_id", "last_purchase")


@query("join_interval", "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts between c.ts and c.ts + interval 1 hour")
def join_interval(spark, sf):
    e = load(spark, sf, "events")
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("c_ts"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("p_ts"))
    return c.join(p, "user_id").where("p_ts between c_ts and c_ts + interval 1 hour").select("click_id", "purchase_id")


STAR = R + ", st as (select r_name as region, n_name as nation, kind, difficulty, concept, correct from roll join supplier on s_suppkey = model join nation on n_nationkey = s_nationkey join region on r_regionkey = n_regionkey) "


def star(spark, sf):
    s, n, r = (load(spark, sf, t) for t in ("supplier", "nation", "region"))
    dim = s.join(F.broadcast(n), s.s_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    dim = dim.select(F.col("s_suppkey").alias("model"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"))
    return G.strict(fx.rollouts(spark, sf)).join(dim, "model")


@query("join_star", STAR + "select region, kind, count(*) as n, round(avg(correct::int), 6) as acc from st group by all")
def join_star(spark, sf):
    return star(spark, sf).groupBy("region", "kind").agg(n_rows(), acc("verdict").alias("acc"))


# -- aggregates and windows


@query("agg_cube", R + "select concept, difficulty, grouping_id(concept, difficulty)::bigint as level, count(*) as n, round(avg(correct::int), 6) as acc from roll group by cube (concept, difficulty)")
def agg_cube(spark, sf):
    return verdicts(spark, sf).cube("concept", "difficulty").agg(F.grouping_id().alias("level"), n_rows(), acc("v1").alias("acc"))


@query("agg_rollup", STAR + "select region, nation, count(*) as n, round(avg(correct::int), 6) as acc from st group by rollup (region, nation)")
def agg_rollup(spark, sf):
    return star(spark, sf).rollup("region", "nation").agg(n_rows(), acc("verdict").alias("acc"))


@query("agg_grouping_sets", R + "select kind, difficulty, seed, count(*) as n, round(avg(correct::int), 6) as acc from roll group by grouping sets ((kind, difficulty), (seed), ())")
def agg_grouping_sets(spark, sf):
    v = verdicts(spark, sf)
    return v.groupingSets([["kind", "difficulty"], ["seed"], []], "kind", "difficulty", "seed").agg(n_rows(), acc("v1").alias("acc")).select("kind", "difficulty", "seed", "n", "acc")


@query("agg_pivot", R + "select model, " + ", ".join(f"round(avg(correct::int) filter (kind = '{k}'), 6) as {k}" for k in KINDS) + " from roll group by model")
def agg_pivot(spark, sf):
    return verdicts(spark, sf).groupBy("model").pivot("kind", KINDS).agg(acc("v1"))


@query("agg_unpivot", R + "select model, kind, round(avg(correct::int), 6) as acc from roll group by all")
def agg_unpivot(spark, sf):
    wide = verdicts(spark, sf).groupBy("model").pivot("kind", KINDS).agg(acc("v1"))
    return wide.unpivot("model", KINDS, "kind", "acc").where("acc is not null")


@query("agg_filtered", "select user_id, count(*) filter (event_type = 'purchase') as yes, count(*) filter (event_type in ('view', 'click')) as no, count(*) filter (event_type = 'error') as errors from events group by user_id")
def agg_filtered(spark, sf):
    n = lambda s: F.count_if(F.col("state") == s)
    return event_states(spark, sf).groupBy("user_id").agg(n("yes").alias("yes"), n("no").alias("no"), n("error").alias("errors"))


@query("win_rank", R + ", a as (select kind, model, round(avg(correct::int), 9) as acc from roll group by all) select kind, model, round(acc, 6) as acc, rank() over w as rank, dense_rank() over w as dense, row_number() over (partition by kind order by acc desc, model) as row_no, round(percent_rank() over w, 6) as pct, round(cume_dist() over w, 6) as cume from a window w as (partition by kind order by acc desc)")
def win_rank(spark, sf):
    a = verdicts(spark, sf).groupBy("kind", "model").agg(F.round(acc("v1"), 9).alias("acc"))
    w = Window.partitionBy("kind").orderBy(F.desc("acc"))
    return a.select("kind", "model", "acc", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.row_number().over(Window.partitionBy("kind").orderBy(F.desc("acc"), "model")).alias("row_no"), F.percent_rank().over(w).alias("pct"), F.cume_dist().over(w).alias("cume"))


@query("win_running_acc", R + ", a as (select model, k, avg(correct::int) as acc from roll group by all) select model, k, round(avg(acc) over (partition by model order by k rows between unbounded preceding and current row), 6) as running from a")
def win_running_acc(spark, sf):
    a = verdicts(spark, sf).groupBy("model", "k").agg(acc("v1").alias("acc"))
    return a.select("model", "k", F.avg("acc").over(Window.partitionBy("model").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)).alias("running"))


@query("win_range", "select event_id, round(sum(value) over (partition by user_id order by ts range between interval 1 day preceding and current row), 4) as day_sum from events")
def win_range(spark, sf):
    e = load(spark, sf, "events").select("event_id", "user_id", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.round(F.sum("value").over(w), 4).alias("day_sum"))


@query("win_lag", R + ", a as (select model, kind, avg(correct::int) as acc from roll group by all) select model, kind, round(acc, 6) as acc, round(acc - lag(acc) over w, 6) as step, round(lead(acc) over w, 6) as next_acc from a window w as (partition by model order by kind)")
def win_lag(spark, sf):
    a = verdicts(spark, sf).groupBy("model", "kind").agg(acc("v1").alias("acc"))
    w = Window.partitionBy("model").orderBy("kind")
    return a.select("model", "kind", "acc", (F.col("acc") - F.lag("acc").over(w)).alias("step"), F.lead("acc").over(w).alias("next_acc"))


@query("win_ntile", "select doc_id, ntile(5) over (partition by source order by md5(doc_id::varchar), doc_id)::int as chunk from documents")
def win_ntile(spark, sf):
    return J.chunks(docs(spark, sf).select("doc_id", "source"), "source", F.col("doc_id")).select("doc_id", "chunk")


# -- functions


@query("fn_string", r"select p_partkey, upper(p_name) as upper_, length(p_name) as len_, len(string_split(p_name, ' ')) as words, regexp_replace(p_name, '[aeiou]', '', 'g') as consonants, levenshtein(p_name, p_brand)::int as dist from part")
def fn_string(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("upper_"), F.length("p_name").alias("len_"), F.size(F.split("p_name", " ")).alias("words"), F.regexp_replace("p_name", "[aeiou]", "").alias("consonants"), F.levenshtein("p_name", "p_brand").alias("dist"))


@query("fn_date", "select date_trunc('quarter', o_orderdate)::date as quarter, count(*) as n, min(date_diff('day', o_orderdate::date, (date_trunc('quarter', o_orderdate) + interval 3 month)::date)) as least_days, count(*) filter (date_diff('day', o_orderdate::date, (date_trunc('quarter', o_orderdate) + interval 3 month)::date) <= 60) as due_60 from orders group by 1")
def fn_date(spark, sf):
    q = F.date_trunc("quarter", "o_orderdate").cast("date")
    days = F.date_diff(F.add_months(q, 3), F.col("o_orderdate").cast("date"))
    return load(spark, sf, "orders").groupBy(q.alias("quarter")).agg(n_rows(), F.min(days).alias("least_days"), F.count(F.when(days <= 60, 1)).alias("due_60"))


@query("fn_array", "select vec_id, len(list_filter(embedding, lambda x: x > 0)) as positive, round(list_sum(list_transform(embedding, lambda x: abs(x::double))), 6) as l1, round(list_max(embedding)::double, 6) as top from embeddings")
def fn_array(spark, sf):
    return load(spark, sf, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.aggregate(F.transform("embedding", lambda x: F.abs(x.cast("double"))), F.lit(0.0), lambda s, x: s + x).alias("l1"), F.array_max("embedding").cast("double").alias("top"))


@query("fn_map", "select p_partkey as prompt_id, case p_partkey % 4 when 0 then 'mcq' when 1 then 'numeric' when 2 then 'multipart' else 'fraction' end as kind, case p_partkey % 4 when 2 then 2 else 1 end as parts from part")
def fn_map(spark, sf):
    p = fx.problems(spark, sf).withColumn("cache", F.create_map(F.col("kind"), F.col("gold")))
    return p.select("prompt_id", F.map_keys("cache")[0].alias("kind"), F.size(F.element_at("cache", F.col("kind"))).alias("parts"))


@query("fn_json", "select (props ->> '$.k')::bigint as k, count(*) as n, round(sum(value), 4) as total from events group by 1")
def fn_json(spark, sf):
    e = load(spark, sf, "events").select(F.from_json("props", "k long").alias("p"), "value")
    return e.groupBy(F.col("p.k").alias("k")).agg(n_rows(), F.round(F.sum("value"), 4).alias("total"))


@query("fn_math", "select p_partkey, greatest(-1.0, least(1.0, p_retailprice / 950 - 1)) as clipped, round(abs(p_retailprice - 950) / 950, 6) as rel_err, round(ln(p_retailprice), 6) as log_ from part")
def fn_math(spark, sf):
    p = F.col("p_retailprice")
    return load(spark, sf, "part").select("p_partkey", F.greatest(F.lit(-1.0), F.least(F.lit(1.0), p / 950 - 1)).alias("clipped"), (F.abs(p - 950) / 950).alias("rel_err"), F.log(p).alias("log_"))


@query("fn_hash", "select doc_id, ('0x' || substr(md5(doc_id::varchar), 1, 8))::bigint % 5 as bucket, sha256(lang || source) as digest from documents")
def fn_hash(spark, sf):
    return docs(spark, sf).select("doc_id", (X.md5_int(F.col("doc_id").cast("string")) % 5).alias("bucket"), F.sha2(F.concat("lang", "source"), 256).alias("digest"))


# -- batch twins of the streams


@query("ev_tumbling", "select user_id, time_bucket(interval 1 hour, ts) as start, count(*) filter (event_type = 'purchase') as yes, count(*) as n from events group by all")
def ev_tumbling(spark, sf):
    from ..streaming.verdicts import windowed

    return windowed(load(spark, sf, "events"), "1 hour").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("ev_sliding", "select user_id, s as start, count(*) filter (event_type = 'purchase') as yes, count(*) as n from (select *, unnest([time_bucket(interval 15 minute, ts), time_bucket(interval 15 minute, ts) - interval 15 minute, time_bucket(interval 15 minute, ts) - interval 30 minute, time_bucket(interval 15 minute, ts) - interval 45 minute]) as s from events) group by all")
def ev_sliding(spark, sf):
    from ..streaming.verdicts import windowed

    return windowed(load(spark, sf, "events"), "1 hour", "15 minutes").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("ev_session", "with g as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 12 hour then 0 else 1 end as new_ from events), s as (select *, sum(new_) over (partition by user_id order by ts rows unbounded preceding) as sid from g) select user_id, min(ts) as start, count(*) filter (event_type = 'purchase') as yes, count(*) as n from s group by user_id, sid")
def ev_session(spark, sf):
    from ..streaming.verdicts import sessions

    return sessions(load(spark, sf, "events"), "12 hours").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("ev_dedup", "select event_id from (select event_id, row_number() over (partition by user_id, event_type, date_trunc('hour', ts) order by ts, event_id) as n from events) where n = 1")
def ev_dedup(spark, sf):
    w = Window.partitionBy("user_id", "event_type", F.date_trunc("hour", "ts")).orderBy("ts", "event_id")
    return load(spark, sf, "events").withColumn("n", F.row_number().over(w)).where("n = 1").select("event_id")


@query("ev_late", "with a as (select ts, event_id as o from events union all select ts, 1000000000 + event_id from events where event_id % 97 = 0), r as (select *, max(ts) over (order by o rows between unbounded preceding and 1 preceding) as top from a) select count(*) as n, count(*) filter (ts < top - interval 10 minute) as late from r")
def ev_late(spark, sf):
    """Rows behind a ten-minute watermark in arrival order. Arrival is cut into parts: the
    latest time before each part comes from a small table, so no task orders all rows."""
    e = load(spark, sf, "events").select(F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("o"))
    a = e.unionAll(e.where("o % 97 = 0").withColumn("o", F.col("o") + 1_000_000_000)).withColumn("part", F.floor(F.col("o") / 5000))
    tops = a.groupBy("part").agg(F.max("ts").alias("m"))
    base = tops.withColumn("base", F.max("m").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).drop("m")  # a row a part
    own = F.max("ts").over(Window.partitionBy("part").orderBy("o").rowsBetween(Window.unboundedPreceding, -1))
    r = a.withColumn("own", own).join(F.broadcast(base), "part").withColumn("top", F.greatest("own", "base"))
    return r.agg(n_rows(), F.count(F.when(F.col("ts") < F.col("top") - F.expr("interval 10 minutes"), 1)).alias("late"))


@F.udtf(returnType="pos int, n int, head string")
class TokenWindows:
    """Windows of ``width`` tokens every ``stride`` of a text; a shorter text is one window."""

    def eval(self, words: list, width: int, stride: int):
        words = words or []
        for at in range(0, max(1, len(words) - width + stride), stride):
            part = words[at : at + width]
            if part:
                yield at, len(part), part[0]


@query("udtf_windows", f"with t as (select doc_id, {S.TOKENS} as t from documents), w as (select doc_id, t, unnest(range(0, greatest(1, len(t) - 60 + 30), 30)) as pos from t) select doc_id, pos, least(60, len(t) - pos) as n, t[pos + 1] as head from w where len(t) - pos > 0")
def udtf_windows(spark, sf):
    d = docs(spark, sf).select("doc_id", X.tokens(X.normalize(F.col("text"))).alias("words"))
    return d.lateralJoin(TokenWindows(F.col("words").outer(), F.lit(60), F.lit(30))).select("doc_id", "pos", "n", "head")


