"""Strict and liberal scoring, policies for failed verdicts, comparisons and reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import answers as A
from .grading import agrees, extracted

PROTOCOLS = {"problem": {"tol": 0.02, "fallback": 600}, "subpart": {"tol": 0.01, "fallback": 0}, "subpart_cached": {"tol": 0.02, "fallback": 300}}


def liberal_problem(rolls: DataFrame, tol: float = 0.02) -> DataFrame:
    """Adds judged: one verdict a record. Its candidates are the boxes, or the numbers of the
    last 600 characters where there is no box."""
    x = extracted(rolls) if "boxes" not in rolls.columns else rolls
    fallback = A.tail_numbers(F.col("response"), 600)
    gold = A.numbers_of(F.when(F.col("kind").isin("numeric", "multipart"), F.col("gold")))
    from_tail = F.forall(gold, lambda g: F.exists(fallback, lambda p: A.close(p.try_cast("double"), g, tol))) & F.col("kind").isin("numeric", "multipart")
    return x.withColumn("judged", F.when(F.size("boxes") > 0, agrees(F.col("boxed"), tol)).otherwise(F.coalesce(from_tail, F.lit(False))))


def subparts(rolls: DataFrame, tol: float = 0.01, fallback: int = 0) -> DataFrame:
    """One row a gold part: is it matched by ANY prediction? Predictions are the parts of
    every box and, with ``fallback``, the numbers of that many last characters if no box."""
    x = extracted(rolls) if "boxes" not in rolls.columns else rolls
    preds = F.flatten(F.transform("boxes", lambda b: A.parts_of(b, F.size("gold"))))
    if fallback:
        preds = F.when(F.size("boxes") > 0, preds).otherwise(A.tail_numbers(F.col("response"), fallback))
    counted = F.col("kind").isin("numeric", "multipart")
    x = x.withColumn("preds", preds).withColumn("_read", A.numbers_of(F.when(counted, F.col("preds")))).withColumn("_wants", A.numbers_of(F.when(counted, F.col("gold"))))
    rows = x.select("*", F.posexplode("gold").alias("part", "want")).withColumn("_want", F.get("_wants", F.col("part")))
    number = F.exists("_read", lambda p: A.close(p, F.col("_want"), tol))
    letter = F.exists("preds", lambda p: A.match_letter(p, F.col("want")))
    exact = F.coalesce(A.symbolic_match(F.when(F.col("kind") == "fraction", F.try_element_at("preds", F.lit(-1))), F.col("want")), F.lit(False))
    return rows.withColumn("part_ok", F.coalesce(F.when(F.col("kind") == "mcq", letter).when(F.col("kind") == "fraction", exact).otherwise(number), F.lit(False))).drop("_read", "_wants", "_want")


def all_parts(parts: DataFrame, keys: list[str]) -> DataFrame:
    """keys, judged (AND over parts) and partial (share of parts)."""
    return parts.groupBy(*keys).agg(F.bool_and("part_ok").alias("judged"), F.avg(F.col("part_ok").cast("int")).alias("partial"))


def liberal_cached(rolls: DataFrame, cache: DataFrame, strict_parts: DataFrame, keys: list[str], tol: float = 0.02) -> DataFrame:
    """Gold parts from a cleaned cache (prompt_id, clean), numbers of the last 300 characters
    as fallback; verdicts that the strict layer gives stay as they are."""
    own = rolls.drop("gold").join(cache.withColumnRenamed("clean", "gold"), "prompt_id")
    parts = subparts(own, tol, 300).select(*keys, "part", "part_ok")
    pinned = strict_parts.select(*keys, "part", F.col("part_ok").alias("pinned"))
    out = parts.join(pinned, [*keys, "part"], "left").withColumn("part_ok", F.coalesce(F.when(F.col("pinned"), True), F.col("part_ok")))
    return all_parts(out, keys)


# -- verdict policies


def parse_verdict(answer: Column) -> Column:
    """yes or no where the answer holds exactly one of the words, else unparseable; null: error."""
    words = F.regexp_extract_all(F.upper(answer), F.lit(r"\b(YES|NO)\b"), F.lit(1))
    return F.when(answer.isNull(), "error").when(F.size(words) != 1, "unparseable").otherwise(F.lower(F.try_element_at(words, F.lit(1))))


def policy_bounds(df: DataFrame, by: list[str], state: str = "state") -> DataFrame:
    """n, judged and the two ends: all failures wrong (low), failures out of the denominator (high)."""
    s = F.col(state)
    n = lambda c: F.sum(c.cast("int")).cast("long")
    out = df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), n(s.isin("yes", "no")).alias("judged"), n(s == "yes").alias("yes"), n(s == "error").alias("errors"), n(s == "unparseable").alias("unparseable"), n(s == "unjudgeable").alias("unjudgeable"))
    return out.withColumn("low", F.col("yes") / F.col("n")).withColumn("high", F.when(F.col("judged") > 0, F.col("yes") / F.col("judged")))


def rejudge(first: DataFrame, second: DataFrame, key: str) -> DataFrame:
    """Errors take the verdict of a second run where it has one."""
    again = second.select(key, F.col("state").alias("_again"))
    return first.join(again, key, "left").withColumn("state", F.when(F.col("state") == "error", F.coalesce("_again", "state")).otherwise(F.col("state"))).drop("_again")


def apply_policy(state: Column, unparseable: str = "wrong", error: str = "wrong", unjudgeable: str = "wrong") -> Column:
    """1, 0, or null for a record that the policy leaves out ('drop')."""
    value = {"wrong": F.lit(0), "drop": F.lit(None).cast("int")}
    return F.when(state == "yes", 1).when(state == "no", 0).when(state == "unparseable", value[unparseable]).when(state == "error", value[error]).otherwise(value[unjudgeable])


def dedup_range(df: DataFrame, keys: list[str], order: list[str], ok: str, by: list[str]) -> DataFrame:
    """Scores under each rule for repeated exports: all rows, first, last, any, every."""
    g = df.groupBy(*by, *keys).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col(ok).cast("int")).alias("s"), F.min(F.struct(*order, ok)).getField(ok).cast("int").alias("first"), F.max(F.struct(*order, ok)).getField(ok).cast("int").alias("last"), F.max(F.col(ok).cast("int")).alias("any"), F.min(F.col(ok).cast("int")).alias("every"))
    return g.groupBy(*by).agg(F.sum("n").alias("rows"), F.count(F.lit(1)).alias("ids"), (F.sum("s") / F.sum("n")).alias("score_none"), *(F.avg(c).alias(f"score_{c}") for c in ("first", "last", "any", "every")))


# -- comparisons


def rank_reversals(scores: DataFrame, a: str, b: str) -> DataFrame:
    """Every pair of models: does the order change between two judges?"""
    x, y = scores.alias("x"), scores.alias("y")
    sign = lambda c: F.signum(F.round(F.col(f"x.{c}") - F.col(f"y.{c}"), 9)).cast("int")
    return x.join(y, F.col("x.model") < F.col("y.model")).select(F.col("x.model").alias("model_1"), F.col("y.model").alias("model_2"), sign(a).alias("sign_a"), sign(b).alias("sign_b"), (sign(a) * sign(b) < 0).alias("reversed"))


def lift_signs(scores: DataFrame, base: Column, a: str, b: str) -> DataFrame:
    """Lift over the base model by two judges, and whether the signs agree."""
    zero = scores.where(base).select(F.col(a).alias("a0"), F.col(b).alias("b0"))
    out = scores.crossJoin(F.broadcast(zero))  # the base is one row
    la, lb = F.col(a) - F.col("a0"), F.col(b) - F.col("b0")
    return out.select("model", la.alias("lift_a"), lb.alias("lift_b"), (F.signum(F.round(la, 9)) == F.signum(F.round(lb, 9))).alias("same_sign"))


def chunks(df: DataFrame, stratum: str, key: Column, n: int = 5) -> DataFrame:
    """Adds chunk 1..n: equal parts of each stratum in md5 order."""
    return df.withColumn("chunk", F.ntile(n).over(Window.partitionBy(stratum).orderBy(F.md5(key.cast("string")), key)))


def stratified(df: DataFrame, stratum: str, key: str, quota: int) -> DataFrame:
    """The first ``quota`` of each stratum in md5 order."""
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(stratum).orderBy(F.md5(F.col(key).cast("string")), key))).where(F.col("_n") <= quota).drop("_n")


def leaderboard(scores: DataFrame, base: int, columns: list[str]) -> DataFrame:
    """model, a column a format, the difference from the base model and the rank in each."""
    wide = scores.groupBy("model").pivot("kind", columns).agg(F.first("acc"))
    zero = wide.where(F.col("model") == base).select(*(F.col(c).alias(f"_{c}") for c in columns))
    out = wide.crossJoin(F.broadcast(zero))  # the base is one row
    w = lambda c: Window.orderBy(F.col(c).desc_nulls_last())  # noqa: E731  a row a model
    return out.select("model", *columns, *((F.col(c) - F.col(f"_{c}")).alias(f"delta_{c}") for c in columns), *(F.dense_rank().over(w(c)).alias(f"rank_{c}") for c in columns))


def failure_kind(boxed: Column, want: Column, kind: Column) -> Column:
    counted = kind.isin("numeric", "multipart")
    p, g = (F.get(A.numbers_of(F.when(counted, x)), F.lit(0)) for x in (A.parts_of(boxed, F.size(want)), want))
    off = F.abs(p - g) / F.abs(g)
    return (
        F.when(boxed.isNull(), "no_box").when(kind == "mcq", "wrong_choice").when(kind == "fraction", "wrong_expression")
        .when(p.isNull(), "not_a_number").when(p * g < 0, "sign").when(off <= 0.05, "within_5").otherwise("magnitude")
    )
