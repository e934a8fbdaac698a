"""Streams end and equal their batch twins; repeated deliveries change nothing."""

import shutil
import uuid

import pytest
from pyspark.sql import functions as F

from clearbound.operators import corpus as C
from clearbound.operators import lexical
from clearbound.sources import fixtures as fx
from clearbound.sources import tables
from clearbound.streaming import audit_stream, verdicts


@pytest.fixture
def events(spark, sf, tmp_path):
    """events in ten files in order of arrival."""
    e = tables.load(spark, sf, "events")
    for i in range(10):
        e.where(f"event_id div 100 = {i}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 2).parquet(str(tmp_path / "in"))
    return e, stream


def finished(df, mode="append", tmp=None):
    name = "t" + uuid.uuid4().hex[:8]
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_windows_equal_batch(events):
    e, stream = events
    assert rows(finished(verdicts.windowed(stream, "1 hour"), "complete")) == rows(verdicts.windowed(e, "1 hour"))
    s = rows(finished(verdicts.windowed(stream, "1 hour", "15 minutes")))
    assert set(s) <= set(rows(verdicts.windowed(e, "1 hour", "15 minutes"))) and s


def test_sessions_equal_batch(events):
    e, stream = events
    s, b = rows(finished(verdicts.sessions(stream, "1 hour"))), rows(verdicts.sessions(e, "1 hour"))
    assert set(s) <= set(b) and len(s) >= 0.8 * len(b)


def test_dedup_and_joins(events):
    e, stream = events
    twice = stream.unionAll(stream)
    assert finished(verdicts.deduplicated(twice, ["event_id"])).count() == e.count()
    pick = lambda d, t: d.where(F.col("event_type") == t)
    s = rows(finished(verdicts.click_to_purchase(pick(stream, "click"), pick(stream, "purchase"))))
    assert s == rows(verdicts.click_to_purchase(pick(e, "click"), pick(e, "purchase")))


def test_running_kappa(events):
    e, stream = events
    pairs = lambda d: d.select((F.col("user_id") % 3).alias("model"), (F.col("value") > 50).cast("int").alias("a"), (F.col("event_id") % 2).cast("int").alias("b"))
    out = finished(verdicts.running_kappa(pairs(stream)), "update")
    from clearbound.operators import stats

    want = {r.model: (r.n, round(r.kappa, 9)) for r in stats.kappa(pairs(e), "a", "b", ["model"]).collect()}
    got = {}
    for r in out.collect():
        got[r.model] = max(got.get(r.model, (0, 0)), (r.n, round(r.kappa, 9)))
    assert got == want


def test_audit_stream_equals_batch(spark, sf, tmp_path):
    t, e = fx.train_docs(spark, sf).select("id", "text"), fx.eval_docs(spark, sf).select("id", "text")
    for i in range(5):
        t.where(f"id % 5 = {i}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(t.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    for again in (1, 2):  # the second run delivers everything again
        shutil.rmtree(tmp_path / "cp", ignore_errors=True)
        audit_stream.audit_batches(stream, e, str(tmp_path / "ledger"), str(tmp_path / "cp")).awaitTermination(180)
        got = rows(spark.read.parquet(str(tmp_path / "ledger")).select("t_id", "e_id", "inter"))
        assert got == rows(lexical.pairs(t, e).select("t_id", "e_id", "inter")), again
    s = finished(audit_stream.lexical_stream(stream, e)).groupBy("t_id", "e_id").count()
    assert rows(s) == rows(lexical.overlaps(t, e).select("t_id", "e_id", "inter"))


def test_formats_round_trip(spark, tmp_path):
    df = spark.createDataFrame([(1, "s", "x\n{y}", "en", None, [("user", "q")], None)], tables.RECORD_SCHEMA)
    tables.write_jsonl(df, str(tmp_path / "j"))
    assert rows(tables.read_jsonl(spark, str(tmp_path / "j"))) == rows(df)
    tables.write_parquet(df, str(tmp_path / "p"), ["language"])
    assert (tmp_path / "p" / "language=en").exists()
    df.select("rec_id", "source").coalesce(1).write.option("header", True).csv(str(tmp_path / "c"))
    assert rows(tables.read_csv(spark, str(tmp_path / "c"), "rec_id long, source string")) == [(1, "s")]
    assert tables.read_lines(spark, str(tmp_path / "c")).count() == 2


def test_corpus(spark, sf):
    import json

    d = tables.load(spark, sf, "documents")
    c = json.loads(C.card(d, "n", "1.0.0", C.licence_of(F.col("text"))).first()[0])
    assert c["records"] == 200 and sum(c["licences"].values()) == 200 and c["version"] == "1.0.0"
    assert (C.bump("1.2.3", False, True), C.bump("1.2.3", True, True), C.bump("1.2.3", False, False)) == ("1.3.0", "2.0.0", "1.2.4")
    assert C.version_diff(d, d, "doc_id").count() == 0
    v = C.violations(spark.createDataFrame([(9, "S"), (1, None)], "difficulty int, length string"))
    assert sorted(r.violations for r in v.collect()) == [["difficulty"], ["length"]]


def test_sql_surface(spark, sf):
    from clearbound.sources import surface

    surface.register(spark, sf)
    r = spark.sql(r"select norm_text('A $\\frac{x}{y}$ [B]') as n, word_tokens('a_1 b!') as t, set_jaccard(array('a','b'), array('b','c')) as j, vector_cosine(array(1D,0D), array(1D,1D)) as c, close_to(101D, 100D, 0.01D) as k, last_boxed('x \\boxed{3}') as b, evaluate_answer('\\frac{1}{4}') as e").first()
    assert (r.n, r.t, r.k, r.b, r.e) == ("a x y b", ["a_1", "b"], True, "3", 0.25) and abs(r.j - 1 / 3) < 1e-9 and abs(r.c - 0.5**0.5) < 1e-9
    assert spark.sql("select count(*) from documents where set_jaccard(word_tokens(norm_text(text)), word_tokens(norm_text(text))) = 1").first()[0] > 190
