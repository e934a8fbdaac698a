"""Verdicts, rewards, advantages, curriculum and objective over logged rollouts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import answers as A

STRICT, FMT, DIM, SYM, CONS = 0.01, 0.10, 0.15, 0.20, -0.25
TERMS = ("r_ans", "r_fmt", "r_dim", "r_sym", "r_cons")


def extracted(rolls: DataFrame) -> DataFrame:
    """Adds boxes and boxed: one Arrow pass over the responses."""
    out = rolls.withColumn("boxes", A.all_boxed("response"))
    return out.withColumn("boxed", F.when(F.size("boxes") > 0, F.element_at("boxes", -1)))


def agrees(pred: Column, tol: float) -> Column:
    """Does an answer text agree with ``gold`` (an array of parts) by ``kind``? Numbers are read
    by the whole ladder: casts, arithmetic and LaTeX, the number before a unit."""
    gold = F.col("gold")
    closed = F.when(F.col("kind").isin("numeric", "multipart"), pred)
    numbers, want = A.numbers_of(A.parts_of(closed, F.size(gold))), A.numbers_of(F.when(closed.isNotNull(), gold))
    multi = (F.size(numbers) == F.size(gold)) & F.forall(F.zip_with(numbers, want, lambda p, g: A.close(p, g, tol)), lambda x: x)
    return F.coalesce(
        F.when(F.col("kind") == "mcq", A.match_letter(pred, gold[0]))
        .when(F.col("kind").isin("numeric", "multipart"), multi)
        .otherwise(F.coalesce(A.symbolic_match(F.when(F.col("kind") == "fraction", pred), gold[0]), F.lit(False))),
        F.lit(False),
    )


def strict(rolls: DataFrame, tol: float = STRICT) -> DataFrame:
    """Adds boxed, boxes and verdict: the last box against the gold."""
    return extracted(rolls).withColumn("verdict", agrees(F.col("boxed"), tol))


def components(rolls: DataFrame) -> DataFrame:
    """The five bounded terms, the binary and the dense reward. With a balance (inflow,
    outflow) the boxed number is held against inflow less outflow."""
    v = rolls if "verdict" in rolls.columns else strict(rolls)
    units = A.unit_tokens(F.col("response"))
    known = F.array(*map(F.lit, A.UNITS))
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda s, x: s + x)
    p, want = F.get(A.numbers_of(F.when(F.col("balance").isNotNull(), A.parts_of(F.col("boxed"), F.lit(1)))), F.lit(0)), total(F.col("balance.inflow")) - total(F.col("balance.outflow"))
    off = F.abs(p - want) / F.greatest(F.abs(want), F.abs(p), F.lit(1e-9)) > 0.05
    out = v.withColumns({
        "r_ans": F.col("verdict").cast("double"),
        "r_fmt": F.when(F.col("boxed").isNotNull(), FMT).otherwise(0.0),
        "r_dim": F.when((F.size(units) > 0) & F.forall(units, lambda u: F.array_contains(known, u)), DIM).otherwise(0.0),
        "r_sym": F.when(A.has_readable_fraction("response"), SYM).otherwise(0.0),
        "r_cons": F.when(F.col("balance").isNotNull() & p.isNotNull() & off, CONS).otherwise(0.0),
    })
    return out.withColumn("r_bin", F.col("r_ans")).withColumn("r_dense", clipped(TERMS))


def clipped(terms) -> Column:
    total = F.lit(0.0)
    for t in terms:
        total = total + F.col(t)
    return F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.round(total, 10)))


def score(rolls: DataFrame, mode: str = "binary") -> DataFrame:
    """Adds r: the binary reward (default) or the clipped dense sum."""
    return components(rolls).withColumn("r", F.col({"binary": "r_bin", "dense": "r_dense"}[mode]))


def dropout(scored: DataFrame) -> DataFrame:
    """Mean dense reward of right and wrong rollouts with each term left out."""
    rows = scored.select("verdict", F.explode(F.array(*(F.struct(F.lit(name).alias("without"), clipped([t for t in TERMS if t != name]).alias("r")) for name in ("none", *TERMS)))).alias("x"))
    return rows.groupBy("x.without").agg(F.avg("x.r").alias("mean_r"), F.avg(F.when(F.col("verdict"), F.col("x.r"))).alias("mean_right"), F.avg(F.when(~F.col("verdict"), F.col("x.r"))).alias("mean_wrong"))


def audit_factor(scored: DataFrame, contaminated: DataFrame, r: str = "r_bin") -> DataFrame:
    """Adds r_audited: zero on contaminated prompts."""
    c = contaminated.select("prompt_id").distinct().withColumn("_c", F.lit(True))
    return scored.join(c, "prompt_id", "left").withColumn("r_audited", F.when(F.col("_c"), 0.0).otherwise(F.col(r))).drop("_c")


def advantage(df: DataFrame, r: str, eps: float = 0.0, group: str = "prompt_id") -> DataFrame:
    """Adds mean_r, sd_r (population) and adv of each group; groups without spread get 0."""
    w = Window.partitionBy(group)
    out = df.withColumn("mean_r", F.avg(r).over(w)).withColumn("sd_r", F.stddev_pop(r).over(w))
    return out.withColumn("adv", F.when(F.col("sd_r") > 1e-12, (F.col(r) - F.col("mean_r")) / (F.col("sd_r") + eps)).otherwise(0.0))


def affine_check(df: DataFrame, r: str, scale: float = 3.0, shift: float = 2.0) -> DataFrame:
    a = advantage(df, r).withColumnRenamed("adv", "adv0").drop("mean_r", "sd_r").withColumn("r2", F.col(r) * scale + shift)
    return advantage(a, "r2").agg(F.count(F.lit(1)).alias("n"), F.max(F.abs(F.col("adv") - F.col("adv0"))).alias("max_diff"))


def flip_stats(scored: DataFrame) -> DataFrame:
    """Ordered pairs within a group that binary ties or orders and dense changes. A group has
    at most K members, so its pairs are made from one array, without a second shuffle."""
    groups = scored.groupBy("prompt_id").agg(F.sort_array(F.collect_list(F.struct("k", "r_bin", "r_dense"))).alias("g"))
    pair = F.flatten(F.transform("g", lambda a, i: F.transform(F.slice("g", i + 2, F.greatest(F.size("g") - i - 1, F.lit(0))), lambda b: F.struct(a["r_bin"].alias("ba"), b["r_bin"].alias("bb"), a["r_dense"].alias("da"), b["r_dense"].alias("db")))))
    p = groups.select(F.explode(pair).alias("p")).select("p.*")
    tied, broken = F.col("ba") == F.col("bb"), F.col("da") != F.col("db")
    n = lambda c: F.sum(c.cast("int")).cast("long")
    out = p.agg(F.count(F.lit(1)).alias("pairs"), n(tied & broken & (F.col("ba") == 0)).alias("ties_broken_wrong"), n(tied & broken & (F.col("ba") == 1)).alias("ties_broken_right"), n((F.col("ba") - F.col("bb")) * (F.col("da") - F.col("db")) < 0).alias("inversions"))
    broken_all = F.col("ties_broken_wrong") + F.col("ties_broken_right") + F.col("inversions")
    return out.withColumn("share_wrong", F.when(broken_all > 0, F.col("ties_broken_wrong") / broken_all))


def closed_form(scored: DataFrame) -> DataFrame:
    """Per mixed prompt: success share, the two advantages in closed form, and how far the
    standardised ones and their unit variance are from it."""
    a = advantage(scored, "r_bin")
    g = a.groupBy("prompt_id").agg(F.avg("r_bin").alias("p"), F.max("adv").alias("hi"), F.min("adv").alias("lo"), F.var_pop("adv").alias("var")).where("p > 0 and p < 1")
    g = g.withColumn("adv_right", F.sqrt((1 - F.col("p")) / F.col("p"))).withColumn("adv_wrong", -F.sqrt(F.col("p") / (1 - F.col("p"))))
    return g.select("prompt_id", "p", "adv_right", "adv_wrong", F.greatest(F.abs(F.col("hi") - F.col("adv_right")), F.abs(F.col("lo") - F.col("adv_wrong"))).alias("gap"), "var")


def dense_bound(scored: DataFrame, delta: float = 0.45) -> DataFrame:
    """Per mixed prompt: the binary advantage of a right rollout and the approximate dense one."""
    g = scored.groupBy("prompt_id").agg(F.avg("r_bin").alias("p")).where("p > 0 and p < 1")
    q = F.col("p") * (1 - F.col("p"))
    return g.select("prompt_id", "p", ((1 - F.col("p")) / F.sqrt(q)).alias("bin_right"), ((1 - F.col("p")) / F.sqrt(q + delta * delta / 12)).alias("dense_right"))


def curriculum(scored: DataFrame, r: str = "r_bin") -> DataFrame:
    """prompt_id, state: always, never or kept."""
    g = scored.groupBy("prompt_id").agg(F.avg(r).alias("p"))
    return g.select("prompt_id", F.when(F.col("p") == 1, "always").when(F.col("p") == 0, "never").otherwise("kept").alias("state"))


def curriculum_report(scored: DataFrame) -> DataFrame:
    n = lambda s: F.sum((F.col("state") == s).cast("int")).cast("long").alias(s)
    return curriculum(scored).agg(F.count(F.lit(1)).alias("prompts"), n("kept"), n("always"), n("never")).withColumn("removed_rate", (F.col("always") + F.col("never")) / F.col("prompts"))


def batches(scored: DataFrame, size: int = 96, parts: int = 64) -> DataFrame:
    """Mixed prompts in md5 order, cut into batches of ``size``; numbered part by part."""
    kept = curriculum(scored).where("state = 'kept'").select("prompt_id", F.md5(F.col("prompt_id").cast("string")).alias("h"))
    kept = kept.withColumn("part", (F.conv(F.substring("h", 1, 4), 16, 10).cast("int") * parts / 65536).cast("int"))
    sums = kept.groupBy("part").agg(F.count(F.lit(1)).alias("c"))
    base = sums.withColumn("base", F.coalesce(F.sum("c").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("c")  # a row a part
    at = F.row_number().over(Window.partitionBy("part").orderBy("h", "prompt_id")) + F.col("base") - 1
    return kept.join(F.broadcast(base), "part").select("prompt_id", F.floor(at / size).cast("long").alias("batch"), (at % size).cast("long").alias("place"))


def epochs(steps: int, batch: int, pool: int) -> float:
    return steps * batch / pool


def sequence_objective(df: DataFrame, adv: str = "adv", lo: float = 0.2, hi: float = 0.2, beta: float = 0.01) -> DataFrame:
    """Per prompt: length-normalised ratio clipped on both sides, mean surrogate, anchor and
    loss, from logged log-probabilities (lp, lp_old, lp_base, len)."""
    w = F.exp((F.col("lp") - F.col("lp_old")) / F.col("len"))
    surrogate = F.least(w * F.col(adv), F.greatest(F.lit(1 - lo), F.least(F.lit(1 + hi), w)) * F.col(adv))
    out = df.withColumn("s", surrogate).withColumn("c", ((w < 1 - lo) | (w > 1 + hi)).cast("int"))
    return out.groupBy("prompt_id").agg(F.avg("s").alias("surrogate"), F.avg(F.col("lp") - F.col("lp_base")).alias("anchor"), F.avg("c").alias("clip_share")).withColumn("loss", -F.col("surrogate") + beta * F.col("anchor"))


def matched_step(runs: DataFrame) -> DataFrame:
    """runs: run (binary, dense), step, score. Both at each step they share, and the difference."""
    a, b = (runs.where(F.col("run") == r).groupBy("step").agg(F.avg("score").alias(r)) for r in ("binary", "dense"))
    return a.join(b, "step").withColumn("delta_pp", 100 * (F.col("binary") - F.col("dense")))


def early_stop(runs: DataFrame) -> DataFrame:
    """The step of the best held-out multiple-choice score, the earlier at ties."""
    s = runs.groupBy("run", "step").agg(F.avg("score").alias("score"))
    return s.groupBy("run").agg(F.max(F.struct("score", (-F.col("step")).alias("s"))).alias("m")).select("run", (-F.col("m.s")).alias("step"), F.col("m.score").alias("score"))
