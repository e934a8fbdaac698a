"""Parsers, match ladder, rewards and advantages: hand cases, the worked group, invariants."""

import math
from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from clearbound.functions import answers as A
from clearbound.operators import grading as G
from clearbound.operators import judging as J
from clearbound.operators import stats as T
from clearbound.sources import fixtures as fx


@pytest.mark.parametrize(("text", "want"), [
    ("\\boxed{1} then \\boxed{\\sqrt{\\frac{T}{2}}}", ["1", "\\sqrt{\\frac{T}{2}}"]), ("none", []), (None, []), ("\\boxed{ok} and \\boxed{open", ["ok"]),
    ("\\boxed{}", []), ("\\boxed{  }", []), ("\\boxed{\\boxed{3}}", ["\\boxed{3}", "3"]),
])
def test_boxes(text, want):
    assert A.boxes(text) == want


@pytest.mark.parametrize(("x", "want"), [
    ("19.6", 19.6), ("\\frac{1}{4}", 0.25), ("2\\times 3", 6), ("\\text{} 5", 5), ("2^3+1", 9), ("3.2 m", 3.2), ("-4e3 J", -4000), ("2\\pi", 2 * math.pi), ("\\sqrt{9}", 3), ("abc", None), ("", None), (None, None), ("1/0", 1), ("9**9**9", 9),
    ("__import__('os')", None), ("\\frac{\\frac{1}{2}}{2}", 0.25),
])
def test_evaluate(x, want):
    got = A.evaluate(x)
    assert got == want or (want is not None and math.isclose(got, want))


@pytest.mark.parametrize(("a", "b", "want"), [
    ("(x+1)^2", "x^2+2*x+1", True), ("\\frac{m g}{k}", "m*g/k", True), ("\\frac{7}{4}", "1.75", True), ("x", "y", False), ("sin(x)^2+cos(x)^2", "1", True), ("sin(x)", "cos(x)", False), ("x/(x*y)", "1/y", True), ("a b", "@@", None),
])
def test_equivalent(a, b, want):
    if a == "\\frac{m g}{k}":
        a = "\\frac{m*g}{k}"
    assert A.equivalent(a, b) is want


def test_plain_and_number(spark):
    df = spark.createDataFrame([("\\frac{3}{4}",), ("12",), ("\\mathrm{5}\\cdot 2",), ("nope",), (None,)], "x string")
    got = [(r.p, r.n) for r in df.select(A.to_plain(F.col("x")).alias("p"), A.number_of(A.to_plain(F.col("x"))).alias("n")).collect()]
    assert got == [("(3)/(4)", 0.75), ("12", 12.0), ("5* 2", 10.0), ("nope", None), (None, None)]


def test_close_edges(spark):
    r = spark.createDataFrame([(101.0, 100.0, True), (101.1, 100.0, False), (-99.0, -100.0, True), (0.0, 0.0, True), (1e-3, 0.0, False), (None, 1.0, False)], "p double, g double, want boolean")
    assert all(x.want == x.got for x in r.select("want", A.close(F.col("p"), F.col("g"), 0.01).alias("got")).collect())


def frame(spark, cases):
    return spark.createDataFrame([(i, i, k, g, t, None) for i, (k, g, t) in enumerate(cases)], "prompt_id long, k long, kind string, gold array<string>, response string, balance struct<inflow:array<double>,outflow:array<double>>")


def test_real_answers(spark):
    """Answers as they are written: fractions, powers, units, commas, wrapped letters."""
    cases = [
        ("numeric", ["0.5"], "\\boxed{\\frac{1}{2}}", True), ("numeric", ["1500"], "\\boxed{1.5\\times 10^{3}}", True), ("numeric", ["9.8"], "\\boxed{9.8 m/s}", True), ("numeric", ["1000"], "\\boxed{1,000}", True),
        ("numeric", ["5"], "\\boxed{2+3}", True), ("mcq", ["B"], "\\boxed{\\text{B}}", True), ("mcq", ["B"], "\\boxed{B) Paris}", True), ("mcq", ["B"], "\\boxed{Because}", False), ("mcq", ["B"], "\\boxed{}", False),
        ("numeric", ["1234567.8"], "\\boxed{1{,}234{,}567.8}", True), ("numeric", ["9.8"], "\\boxed{g = 9.8\\,\\mathrm{m}}", True), ("numeric", ["50"], "\\boxed{50\\%}", True), ("numeric", ["1"], "\\boxed{1,000}", False),
        ("multipart", ["105", "200"], "\\boxed{105,200}", True), ("multipart", ["1234.5", "3"], "\\boxed{1,234.5; 3}", True), ("multipart", ["0.5", "1200"], "\\boxed{\\frac{1}{2}, 1.2\\cdot 10^3}", True), ("multipart", ["1", "2"], "\\boxed{1, 2, 3}", False),
        ("numeric", ["5"], "\\boxed{five}", False), ("numeric", ["5"], "\\boxed{1/0}", False),
    ]
    rows = frame(spark, [c[:3] for c in cases])
    got = {r.prompt_id: r.verdict for r in G.strict(rows).collect()}
    assert [got[i] for i in range(len(cases))] == [c[3] for c in cases]
    lenient = {r.prompt_id: r.judged for r in J.liberal_problem(rows).collect()}
    parts = {r.prompt_id: r.judged for r in J.all_parts(J.subparts(rows), ["prompt_id"]).collect()}
    for i, (*_, want) in enumerate(cases):
        assert lenient[i] == want and (parts[i] or not want)


def test_balance_reads_units(spark):
    rows = spark.createDataFrame([(1, 1, "numeric", ["10"], "\\boxed{10 m}", ([20.0], [10.0])), (2, 1, "numeric", ["10"], "\\boxed{\\frac{40}{2} m}", ([20.0], [10.0]))], "prompt_id long, k long, kind string, gold array<string>, response string, balance struct<inflow:array<double>,outflow:array<double>>")
    assert {r.prompt_id: r.r_cons for r in G.components(rows).collect()} == {1: 0.0, 2: G.CONS}


def test_ladder(spark):
    cases = [("mcq", ["B"], "\\boxed{(b)}", True), ("mcq", ["B"], "\\boxed{C}", False), ("numeric", ["19.6"], "\\boxed{19.7}", True), ("numeric", ["19.6"], "\\boxed{19.8}", False), ("numeric", ["0"], "\\boxed{0}", True),
             ("multipart", ["1", "2"], "\\boxed{1; 2}", True), ("multipart", ["1", "2"], "\\boxed{2; 1}", False), ("multipart", ["1", "2"], "\\boxed{1}", False), ("fraction", ["\\frac{7}{4}"], "\\boxed{\\frac{14}{8}}", True), ("numeric", ["5"], "no box", False)]
    got = {r.prompt_id: r.verdict for r in G.strict(frame(spark, [c[:3] for c in cases])).collect()}
    assert [got[i] for i in range(len(cases))] == [c[3] for c in cases]


def test_worked_group(spark):
    """Eight rollouts of one prompt: the rewards, and the advantages as they compute with the
    population deviation (the printed dense ones are on no single scale)."""
    lead = ["A path of 3 m gives \\frac{1}{2}. ", "A path of 3 m. ", "So \\frac{1}{2}. ", ""]
    cases = [("numeric", ["19.6"], t + "\\boxed{19.6}") for t in lead] + [("numeric", ["19.6"], lead[0] + "\\boxed{42.0}"), ("numeric", ["19.6"], lead[1] + "\\boxed{19.8}"), ("numeric", ["19.6"], lead[2] + "\\boxed{42.0}"), ("numeric", ["19.6"], "rambling")]
    df = frame(spark, cases).withColumn("prompt_id", F.lit(1))
    s = G.components(df)
    r = {x.k: x for x in s.collect()}
    assert [r[i].r_bin for i in range(8)] == [1, 1, 1, 1, 0, 0, 0, 0]
    assert [round(r[i].r_dense, 2) for i in range(8)] == [1, 1, 1, 1, 0.45, 0.25, 0.30, 0]
    a = {x.k: x for x in G.advantage(s, "r_dense").collect()}
    assert math.isclose(a[0].mean_r, 0.625) and round(a[0].sd_r, 4) == 0.3921
    assert [round(a[i].adv, 3) for i in range(8)] == [0.956] * 4 + [-0.446, -0.956, -0.829, -1.594]
    b = {x.k: x.adv for x in G.advantage(s, "r_bin").collect()}
    assert [b[i] for i in range(8)] == [1] * 4 + [-1] * 4
    f = G.flip_stats(s).first()
    assert (f.pairs, f.ties_broken_wrong, f.ties_broken_right, f.inversions) == (28, 6, 0, 0)


def test_reward_invariants(spark, sf):
    s = G.components(fx.rollouts(spark, sf)).cache()
    r = s.agg(F.min("r_dense").alias("lo"), F.max("r_dense").alias("hi"), F.min(F.when(F.col("verdict"), F.col("r_dense"))).alias("right"), F.max(F.when(~F.col("verdict"), F.col("r_dense"))).alias("wrong"), F.countDistinct("r_bin").alias("values")).first()
    assert -1 <= r.lo and r.hi <= 1 and r.right >= 0.85 and r.wrong <= 0.4501 and r.values == 2
    assert G.flip_stats(s).first().inversions == 0
    g = G.advantage(s, "r_dense").groupBy("prompt_id").agg(F.abs(F.sum("adv")).alias("s")).agg(F.max("s")).first()[0]
    assert g < 1e-9
    assert G.affine_check(s.select("prompt_id", "k", "r_dense"), "r_dense").first().max_diff < 1e-9
    c = G.closed_form(s).agg(F.max("gap").alias("gap"), F.max(F.abs(F.col("var") - 1)).alias("v")).first()
    assert c.gap < 1e-9 and c.v < 1e-9
    d = G.dense_bound(s).where("dense_right >= bin_right").count()
    assert d == 0 and round(G.epochs(60, 96, 2268), 1) == 2.5


def test_liberal_layers(spark, sf):
    b = G.extracted(fx.rollouts(spark, sf))
    v = b.select(G.agrees(F.col("boxed"), 0.01).alias("a"), G.agrees(F.col("boxed"), 0.02).alias("b"))
    assert v.where("a and not b").count() == 0
    p = J.all_parts(J.subparts(b), ["prompt_id", "k"])
    assert p.where("judged and partial < 1").count() == 0 and p.where("partial < 0 or partial > 1").count() == 0


def test_policies(spark):
    df = spark.createDataFrame([("m", "YES"), ("m", "no."), ("m", "yes and no"), ("m", None), ("m", "perhaps")], "model string, said string").withColumn("state", J.parse_verdict(F.col("said")))
    r = J.policy_bounds(df, ["model"]).first()
    assert (r.n, r.judged, r.errors, r.unparseable, r.low, r.high) == (5, 2, 1, 2, 0.2, 0.5)
    first, second = df.withColumn("key", F.lit(1)), spark.createDataFrame([(1, "yes")], "key int, state string")
    assert J.rejudge(first, second, "key").where("state = 'error'").count() == 0


def test_kappa_properties(spark):
    df = spark.createDataFrame([("x", "x"), ("y", "y"), ("x", "y"), ("z", "z")], "a string, b string")
    same = T.kappa(df, "a", "a").first()
    assert same.kappa == 1 and -1 <= T.kappa(df, "a", "b").first().kappa < 1
    assert T.kappa(df.where("a = 'x' and b = 'x'"), "a", "b").first().kappa == 1


def test_spearman_ties(spark):
    import numpy as np
    import pandas as pd

    rng = np.random.default_rng(1)
    x = pd.DataFrame({"x": rng.integers(0, 9, 500) / 8, "y": rng.integers(0, 30, 500) / 4})
    got = T.spearman(spark.createDataFrame(x), "x", "y").first()
    assert math.isclose(got.spearman, x["x"].rank().corr(x["y"].rank()), abs_tol=1e-9) and got.n == 500


def test_ranges_and_sets(spark):
    d = J.dedup_range(spark.createDataFrame([(1, 1, 0), (1, 2, 1), (2, 1, 1)], "id int, k int, ok int").withColumn("g", F.lit("g")), ["id"], ["k"], "ok", ["g"]).first()
    assert (d.rows, d.ids, d.score_first, d.score_last, d.score_any, d.score_every) == (3, 2, 0.5, 1, 1, 0.5)
    o = T.set_overlap(spark.createDataFrame([(1,), (2,)], "i int"), spark.createDataFrame([(2,)], "i int"), "i").first()
    assert (o.both, o.set_jaccard, o.subset) == (1, 0.5, True)


def test_mcnemar_models_and_rollouts(spark, sf):
    from clearbound import plans

    rows = G.extracted(fx.rollouts(spark, sf)).select("kind", G.agrees(F.col("boxed"), 0.01).alias("a"), G.agrees(F.col("boxed"), 0.02).alias("b")).collect()
    got = {r.kind: r for r in plans.QUERIES["mcnemar"](spark, sf).collect()}
    assert set(got) == {r.kind for r in rows} and sum(r.n_pairs for r in got.values()) == fx.rollouts(spark, sf).count()
    for kind, r in got.items():
        own = [(bool(x.a), bool(x.b)) for x in rows if x.kind == kind]
        only_a, only_b = own.count((True, False)), own.count((False, True))
        n = only_a + only_b
        p = min(1.0, 2 * sum(math.comb(n, i) for i in range(min(only_a, only_b) + 1)) / 2**n)
        assert (r.n_pairs, r.only_a, r.only_b) == (len(own), only_a, only_b) and math.isclose(r.p, p, abs_tol=1e-6)


def test_group_profile_models(spark, sf):
    from clearbound import plans

    assert {r.model for r in plans.QUERIES["group_profile"](spark, sf).collect()} == {r.model for r in fx.rollouts(spark, sf).select("model").distinct().collect()}


def test_half_tail_is_exact_beyond_1000(spark):
    pairs = [(0, 0), (0, 1), (1, 5), (3, 13), (500, 500), (480, 521), (530, 600), (1000, 1001), (1480, 1620), (4900, 5100), (0, 3000), (20000, 20300)]
    got = spark.createDataFrame(pairs, "b long, c long").select("b", "c", T.half_tail(F.col("b"), F.col("c")).alias("p")).collect()
    for r in got:
        n, term, total = r.b + r.c, 1, 1
        for i in range(1, min(r.b, r.c) + 1):
            term = term * (n - i + 1) // i
            total += term
        assert math.isclose(r.p, float(Fraction(total, 2**n)), rel_tol=1e-8, abs_tol=1e-300)
