"""Pools, vectors and rollouts made from the given tables. Nothing here is random: splits
and plants are arithmetic or md5. Effects in the rollouts are planted, so results on them
test arithmetic and not any claim about models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import md5_int
from .tables import load


def in_eval(doc_id: Column) -> Column:
    return md5_int(doc_id.cast("string")) % 5 == 0


def pool_of(source: Column) -> Column:
    return F.concat(F.lit("P"), F.floor(F.substring(source, 4, 10).cast("int") / 4).cast("string"))


def train_docs(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").where(~in_eval(F.col("doc_id"))).select(F.col("doc_id").alias("id"), "text", "lang", "source", pool_of(F.col("source")).alias("pool"))


def eval_docs(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").where(in_eval(F.col("doc_id"))).select(F.col("doc_id").alias("id"), "text", "lang", "source")


def bench(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "benchmark").select(F.col("item_id").alias("id"), "text")


def memberships(evals: DataFrame) -> DataFrame:
    """Overlapping eval splits: each language, and all."""
    return evals.select("id", F.explode(F.array("lang", F.lit("all"))).alias("eval"))


def six_evals(spark: SparkSession, sf: str) -> DataFrame:
    """Eval documents, and the benchmark's passages as a split of its own with ids below 0."""
    passages = bench(spark, sf).select((-1 - F.col("id")).alias("id"), "text", F.lit("benchmark").alias("lang"))
    return eval_docs(spark, sf).select("id", "text", "lang").unionByName(passages)


def six_memberships(evals: DataFrame) -> DataFrame:
    """``memberships`` of documents; a passage is in the benchmark alone."""
    return evals.select("id", F.explode(F.when(F.col("id") < 0, F.array("lang")).otherwise(F.array("lang", F.lit("all")))).alias("eval"))


def train_lines(spark: SparkSession, sf: str) -> DataFrame:
    t = train_docs(spark, sf)
    return t.select("id", F.posexplode(F.split("text", "\n")).alias("pos", "text"))


# -- rollouts

ROW_ORDER = ["l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice", "l_shipdate"]
KINDS = ("mcq", "numeric", "multipart", "fraction")


def problems(spark: SparkSession, sf: str) -> DataFrame:
    p = load(spark, sf, "part")
    kind = F.element_at(F.array(*map(F.lit, KINDS)), (F.col("p_partkey") % 4 + 1).cast("int"))
    letter = F.substring(F.lit("ABCD"), F.col("p_size") % 4 + 1, F.lit(1))
    price, size = F.format_string("%.2f", "p_retailprice"), F.col("p_size").cast("string")
    gold = F.when(kind == "mcq", F.array(letter)).when(kind == "numeric", F.array(price)).when(kind == "multipart", F.array(price, size)).otherwise(F.array(F.format_string("\\frac{%d}{4}", "p_size")))
    return p.select(
        F.col("p_partkey").alias("prompt_id"), kind.alias("kind"), gold.alias("gold"), (F.floor((F.col("p_size") - 1) / 5) + 1).cast("int").alias("difficulty"),
        F.col("p_type").alias("concept"), F.col("p_brand").alias("source"), F.round("p_retailprice", 2).alias("price"), F.col("p_size").alias("size"),
        F.when(kind == "numeric", F.struct(F.array(F.round("p_retailprice", 2) * 2).alias("inflow"), F.array(F.round("p_retailprice", 2)).alias("outflow"))).alias("balance"),
    )


def rollouts(spark: SparkSession, sf: str, most: int = 16) -> DataFrame:
    """One row for each (prompt, k): what was planted, the response text and the log. A
    multi-part answer that is off by half has its second part right, for partial credit."""
    items = load(spark, sf, "lineitem")
    k = F.row_number().over(Window.partitionBy("l_partkey").orderBy(*ROW_ORDER))
    h = (F.col("l_orderkey") * 7 + F.col("l_linenumber") * 13 + F.col("l_suppkey") * 3) % 100 + F.when(F.col("l_linestatus") == "F", 8).otherwise(0)
    skill = F.lit(45) + (F.col("l_suppkey") * 37) % 50 - F.col("difficulty") * 5
    rows = items.withColumn("k", k).where(F.col("k") <= most).join(problems(spark, sf), F.col("l_partkey") == F.col("prompt_id"))
    rows = rows.withColumn("h", h).withColumn("correct", F.col("h") < skill)
    right = F.when(F.col("h") % 3 == 0, 0.0).when(F.col("h") % 3 == 1, 0.005).otherwise(-0.004)
    wrong = F.when(F.col("h") % 4 == 0, 0.015).when(F.col("h") % 4 == 1, 0.03).when(F.col("h") % 4 == 2, 0.5)
    rows = rows.withColumn("error", F.when(F.col("correct"), right).otherwise(wrong))
    step = F.when(F.col("correct"), 0).otherwise(1)
    number = lambda c: F.format_string("%.4f", F.col(c) * (1 + F.col("error")))
    # how an answer is written: plain, with a unit, as a power of ten, with commas of thousands, as a fraction
    form, value = F.col("l_orderkey") % 5, F.col("price") * (1 + F.col("error"))
    written = (
        F.when(form == 1, F.concat(number("price"), F.lit(" m")))
        .when(form == 2, F.format_string("%.7f \\times 10^{3}", value / 1000))
        .when(form == 3, F.format_number(value, 4))
        .when(form == 4, F.format_string("\\frac{%d}{10000}", F.round(value * 10000).cast("long")))
        .otherwise(number("price"))
    )
    letter = F.substring(F.lit("ABCD"), (F.col("size") + step) % 4 + 1, F.lit(1))
    answer = (
        F.when(F.col("kind") == "mcq", F.when(form == 1, F.format_string("\\text{%s}", letter)).when(form == 2, F.format_string("(%s)", letter)).otherwise(letter))
        .when(F.col("kind") == "numeric", written)
        .when(F.col("kind") == "multipart", F.concat(F.when(form == 3, F.format_number(value, 4)).otherwise(number("price")), F.lit("; "), F.when(F.col("error") == 0.5, F.format_string("%.4f", F.col("size").cast("double"))).otherwise(number("size"))))
        .otherwise(F.format_string("\\frac{%d}{4}", F.col("size") + step))
    )
    shape = F.col("l_linenumber") % 4
    lead = (
        F.when(shape == 0, F.lit("A length of 3.2 m over 1.5 s gives \\frac{1}{7} of the path. "))
        .when(shape == 1, F.lit("The load is 12 kg and acts for 4 s. "))
        .when(shape == 2, F.lit("Half of it, \\frac{x}{2}, remains. "))
        .otherwise(F.lit(""))
    )
    tail = F.when(F.col("error").isNull(), F.lit("No answer could be reached.")).otherwise(F.concat(F.lit("First try \\boxed{0}, then answer is \\boxed{"), answer, F.lit("}.")))
    seed = F.when(F.col("l_suppkey") % 3 == 0, 42).when(F.col("l_suppkey") % 3 == 1, 17).otherwise(23)
    return rows.select(
        "prompt_id", "k", "kind", "gold", "difficulty", "concept", "source", "price", "size", "balance", F.col("l_suppkey").alias("model"), seed.alias("seed"), F.col("l_linestatus").alias("arm"), shape.cast("int").alias("shape"), "h", "correct",
        F.concat(lead, tail).alias("response"), "l_orderkey", "l_linenumber", "l_returnflag", (F.lit(10) * (1 + F.floor(F.col("l_quantity") / 9))).cast("int").alias("step"),
        (-F.col("l_quantity") / 10).alias("lp"), (-F.col("l_quantity") / 10 + F.col("l_discount") - 0.05).alias("lp_old"), (-F.col("l_quantity") / 10 + F.col("l_tax") - 0.04).alias("lp_base"), (F.col("l_linenumber") + 1).alias("len"),
    )


def planted_vectors(spark: SparkSession, sf: str) -> DataFrame:
    """Train vectors of which a fifth are moved close to an eval vector by a known share."""
    e = load(spark, sf, "embeddings")
    near = e.where("vec_id % 5 = 0").select((F.col("vec_id") + 1).alias("vec_id"), F.col("embedding").alias("other"))
    share = F.element_at(F.array(F.lit(0.85), F.lit(0.75), F.lit(0.65), F.lit(0.60)), (F.floor(F.col("vec_id") / 5) % 4 + 1).cast("int"))
    mixed = F.zip_with("embedding", "other", lambda x, y: share * y.cast("double") + (1 - share) * x.cast("double"))
    v = F.when(F.col("other").isNotNull(), mixed).otherwise(F.col("embedding").cast("array<double>"))
    return e.where("vec_id % 5 <> 0").join(near, "vec_id", "left").select(F.col("vec_id").alias("id"), v.alias("vec"))
