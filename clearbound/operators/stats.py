"""Agreement, paired tests, ranks and rates as aggregates and closed forms."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def kappa(df: DataFrame, a: str, b: str, by: list[str] | None = None) -> DataFrame:
    """Cohen's kappa of two categorical columns, for any number of classes: n, agree, kappa
    (1 where both raters always give one same class)."""
    by = by or []
    cells = df.where(F.col(a).isNotNull() & F.col(b).isNotNull()).groupBy(*by, F.col(a).cast("string").alias("a"), F.col(b).cast("string").alias("b")).agg(F.count(F.lit(1)).alias("c"))
    total = cells.groupBy(*by).agg(F.sum("c").alias("n"), F.sum(F.when(F.col("a") == F.col("b"), F.col("c")).otherwise(0)).alias("same"))
    left = cells.groupBy(*by, F.col("a").alias("cls")).agg(F.sum("c").alias("na"))
    right = cells.groupBy(*by, F.col("b").alias("cls")).agg(F.sum("c").alias("nb"))
    chance = left.join(right, [*by, "cls"]).groupBy(*by).agg(F.sum(F.col("na") * F.col("nb")).alias("prod"))
    out = total.join(chance, by, "left") if by else total.crossJoin(chance)
    po, pe = F.col("same") / F.col("n"), F.coalesce(F.col("prod"), F.lit(0)) / (F.col("n") * F.col("n"))
    return out.select(*by, "n", po.alias("agree"), F.when(pe == 1, 1.0).otherwise((po - pe) / (1 - pe)).alias("kappa"))


def kappa_from_margins(n: float, agree: float, a_yes: float, b_yes: float) -> float:
    """Two-class kappa from the agreement rate and the two rates of yes."""
    pe = a_yes * b_yes + (1 - a_yes) * (1 - b_yes)
    return 1.0 if pe == 1 else (agree - pe) / (1 - pe)


def half_tail(b: Column, c: Column) -> Column:
    """P(X <= min(b, c)), X binomial of n = b + c and 1/2, summed from exact ratios; beyond
    n = 1000, where the sums would leave a double, in log space."""
    n, m = (b + c).cast("double"), F.least(b, c).cast("int")
    first = F.struct(F.lit(1.0).alias("term"), F.lit(1.0).alias("sum"))
    step = lambda s, i: F.struct((s["term"] * (n - i + 1) / i).alias("term"), (s["sum"] + s["term"] * (n - i + 1) / i).alias("sum"))
    steps = F.when(m >= 1, F.sequence(F.lit(1), m)).otherwise(F.array().cast("array<int>"))
    exact = F.aggregate(steps, first, step)["sum"] * F.pow(F.lit(2.0), -n)

    def log_step(s: Column, i: Column) -> Column:
        term = s["term"] + F.log((n - i + 1) / i)
        return F.struct(term.alias("term"), (F.greatest(s["sum"], term) + F.log1p(F.exp(-F.abs(s["sum"] - term)))).alias("sum"))

    zero = F.struct(F.lit(0.0).alias("term"), F.lit(0.0).alias("sum"))
    return F.when(n <= 1000, exact).otherwise(F.exp(F.aggregate(steps, zero, log_step)["sum"] - n * F.log(F.lit(2.0))))


def mcnemar(df: DataFrame, a: str, b: str, by: list[str] | None = None) -> DataFrame:
    """Discordant counts of two 0/1 columns and the exact two-sided p."""
    return paired(df, a, b, by).select(*(by or []), "n_pairs", "only_a", "only_b", F.col("p_two").alias("p"))


def paired(df: DataFrame, a: str, b: str, by: list[str] | None = None) -> DataFrame:
    """n_pairs, only_a, only_b, delta_pp, and the sign test one- and two-sided."""
    x, y = F.col(a).cast("int"), F.col(b).cast("int")
    n = lambda c: F.coalesce(F.sum(c.cast("int")), F.lit(0)).cast("long")
    out = df.groupBy(*(by or [])).agg(F.count(F.lit(1)).alias("n_pairs"), n((x == 1) & (y == 0)).alias("only_a"), n((x == 0) & (y == 1)).alias("only_b"), (100 * (F.avg(x) - F.avg(y))).alias("delta_pp"))
    tail = half_tail(F.col("only_a"), F.col("only_b"))
    return out.withColumn("p_one", F.least(F.lit(1.0), tail)).withColumn("p_two", F.least(F.lit(1.0), 2 * tail))


def average_ranks(df: DataFrame, x: str, name: str) -> DataFrame:
    """Average ranks with ties from counts of values. Running totals go over parts of the
    value range, so no task sorts all values."""
    counts = df.groupBy(F.col(x).alias("v")).agg(F.count(F.lit(1)).alias("c"))
    edges = counts.agg(F.percentile_approx("v", [i / 64 for i in range(1, 64)])).first()[0] or []
    part = F.lit(0)
    for e in sorted(set(edges)):
        part = part + (F.col("v") >= F.lit(e)).cast("int")
    parts = counts.withColumn("part", part)
    sums = parts.groupBy("part").agg(F.sum("c").alias("s"))
    base = sums.withColumn("base", F.coalesce(F.sum("s").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("s")  # a row a part
    before = F.coalesce(F.sum("c").over(Window.partitionBy("part").orderBy("v").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranks = parts.withColumn("before", before).join(F.broadcast(base), "part")
    return ranks.select("v", (F.col("base") + F.col("before") + (F.col("c") + 1) / 2).alias(name))


def spearman(df: DataFrame, x: str, y: str) -> DataFrame:
    rx, ry = average_ranks(df, x, "rx").withColumnRenamed("v", x), average_ranks(df, y, "ry").withColumnRenamed("v", y)
    return df.join(rx, x).join(ry, y).agg(F.count(F.lit(1)).alias("n"), F.corr("rx", "ry").alias("spearman"), F.corr(x, y).alias("pearson"))


def wilson(hits: Column, n: Column, z: float = 1.959963984540054) -> tuple[Column, Column]:
    """Interval of a rate."""
    p, zz = hits / n, z * z
    mid, half = (p + zz / (2 * n)) / (1 + zz / n), z * F.sqrt(p * (1 - p) / n + zz / (4 * n * n)) / (1 + zz / n)
    return mid - half, mid + half


def set_overlap(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """n1, n2, both, set_jaccard and whether b lies in a."""
    j = a.select(key).distinct().withColumn("x", F.lit(1)).join(b.select(key).distinct().withColumn("y", F.lit(1)), key, "full")
    out = j.agg(F.count("x").alias("n1"), F.count("y").alias("n2"), F.count(F.col("x") + F.col("y")).alias("both"))
    return out.withColumn("set_jaccard", F.col("both") / (F.col("n1") + F.col("n2") - F.col("both"))).withColumn("subset", F.col("both") == F.col("n2"))


def precision_recall(df: DataFrame, truth: str, said: str, by: list[str] | None = None) -> DataFrame:
    t, s = F.col(truth).cast("int"), F.col(said).cast("int")
    out = df.groupBy(*(by or [])).agg(F.count(F.lit(1)).alias("n"), F.sum(t).cast("long").alias("positives"), F.sum(s).cast("long").alias("flagged"), F.sum(t * s).cast("long").alias("hits"))
    return out.withColumn("precision", F.when(F.col("flagged") > 0, F.col("hits") / F.col("flagged"))).withColumn("recall", F.when(F.col("positives") > 0, F.col("hits") / F.col("positives")))


@F.pandas_udf(DoubleType())
def kappa_of_cells(a: pd.Series, b: pd.Series, c: pd.Series) -> float:
    """Kappa of a contingency table given as cells."""
    n = c.sum()
    pe = sum(c[a == k].sum() * c[b == k].sum() for k in set(a) | set(b)) / n**2
    return 1.0 if pe == 1 else float((c[a == b].sum() / n - pe) / (1 - pe))
