"""The registered queries of these operators, and their SQL where SQL can say it."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, embed_dedup, langid, packing, quality, sharding, simhash, substring, topk, toxicity
from .common import fold, table

#: Labelled rows that a classifier is fitted on, about.
FIT_ROWS = 20_000


def fitted_toxicity(spark: SparkSession, sf_dir: str) -> toxicity.ToxicityModel:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return toxicity.fit_toxicity(toxicity.training_rows(docs, labels, "toxic", (3, 1), FIT_ROWS))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    model = fitted_toxicity(spark, sf_dir)
    scored = toxicity.score_toxicity(table(spark, sf_dir, "documents"), model)
    return scored.select("doc_id", (fold("doc_id", 3) == 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"), "raw")


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.remove_repeats(table(spark, sf_dir, "documents"), window=13, block=7, texts=False)


def op3_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed_dedup.near_vectors(table(spark, sf_dir, "embeddings"), cosine=0.93)


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def fitted_quality(spark: SparkSession, sf_dir: str) -> quality.QualityModel:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return quality.fit_quality(toxicity.training_rows(docs, labels, "quality", (5, 0), FIT_ROWS))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = quality.score_quality(table(spark, sf_dir, "documents"), fitted_quality(spark, sf_dir))
    return scored.select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def fitted_langid(docs: DataFrame) -> langid.LanguageModel:
    return langid.fit_langid(docs.where(F.col("doc_id").isNotNull() & (fold("doc_id", 3) != 1)))


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = langid.predict_language(docs, fitted_langid(docs))
    return found.select("doc_id", (fold("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score", "nats_per_char", "accepted")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), 2048)


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(table(spark, sf_dir, "documents"), 40)


def op9_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(table(spark, sf_dir, "embeddings"))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_documents(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import pipeline as stages

    return stages.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_toxicity, op2_substring_dedup, op3_embedding_dedup, op4_byte_bpe, op5_quality, op6_language, op7_packing, op8_sharding, op9_topk, op10_simhash, pipeline)}

OP2_SQL = r"""
with words as (
  select doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') as w from documents
), starts as (
  select doc_id, p, array_to_string(w[p : p + 12], ' ') as gram
  from (select doc_id, w, unnest(range(1, len(w) - 11)) as p from words where len(w) >= 13)
), firsts as (select gram, min(doc_id) as least from starts group by gram),
hit as (select s.doc_id, s.p from starts s join firsts f using (gram) where s.doc_id > f.least),
gone as (select distinct doc_id, p + k as q from hit, range(0, 13) as t(k)),
each_word as (select doc_id, unnest(w) as word, unnest(range(1, len(w) + 1)) as q from words),
kept as (
  select e.doc_id, string_agg(e.word, ' ' order by e.q) filter (where g.q is null) as kept_text, count(g.q) as n_removed
  from each_word e left join gone g on e.doc_id = g.doc_id and e.q = g.q group by e.doc_id
)
select w.doc_id, len(w.w)::bigint as n_words, coalesce(k.n_removed, 0)::bigint as n_removed, sha256(coalesce(k.kept_text, '')) as kept_sha256
from words w left join kept k on w.doc_id = k.doc_id
"""

OP9_SQL = """
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(1024 * x::double)::bigint) as e from embeddings
  where embedding is not null and vec_id is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), s as (
  select q.vec_id as query_id, c.vec_id, list_sum(list_transform(range(1, least(len(q.e), len(c.e)) + 1), lambda i: q.e[i] * c.e[i]))::bigint as score
  from v q join v c on q.vec_id % 100 = 0 and c.vec_id <> q.vec_id
)
select query_id, rank::int as rank, vec_id, score from (
  select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s
) where rank <= 10
"""

OP3_SQL = """
with recursive v as (
  select vec_id, label, list_transform(embedding, lambda x: x::double) as e from embeddings
), ok as (
  select vec_id, label, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) as n from v
  where label is not null and e is not null and len(e) > 0 and len(list_filter(e, lambda x: x is null or not isfinite(x))) = 0
), links as (
  select a.vec_id as a, b.vec_id as b from ok a join ok b on a.label = b.label and a.vec_id <> b.vec_id and len(a.e) = len(b.e)
  where a.n > 0 and b.n > 0 and list_sum(list_transform(range(1, len(a.e) + 1), lambda i: a.e[i] * b.e[i])) >= 0.93 * a.n * b.n
), reach as (
  select a as node, a as seen from links union select r.node, l.b from reach r join links l on l.a = r.seen
), low as (select node, min(seen) as component_id from reach group by node),
n as (select a as node, count(*) as n_links from links group by a)
select vec_id, coalesce(n_links, 0) as n_links, coalesce(component_id, vec_id) as component_id, coalesce(component_id, vec_id) = vec_id as kept
from v left join low on low.node = vec_id left join n on n.node = vec_id
"""

ORACLE_SQL = {"op2_substring_dedup": OP2_SQL, "op3_embedding_dedup": OP3_SQL, "op9_topk": OP9_SQL}
