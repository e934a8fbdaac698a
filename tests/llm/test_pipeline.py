"""The pipeline on planted rows: copies, passages and junk go, clean documents stay."""

import random

import pytest

pytest.importorskip("clearbound.llm")
import corpus_pipeline as P  # noqa: E402

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("stages")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    long = [r for r in docs.where("lang = 'en' and n_chars between 900 and 3000 and not text rlike '[|$!%*]'").orderBy("doc_id").limit(60).collect()]
    rng = random.Random(4)
    planted, passage = [], " ".join(long[0].text.split()[:70])
    for i, r in enumerate(long[1:20]):
        w = r.text.split()
        w[len(w) // 2] = "changedword"
        planted += [(100000 + i, r.text, r.lang, r.source, r.n_chars), (200000 + i, " ".join(w), r.lang, r.source, r.n_chars)]
    planted += [(300000, "", "en", "s", 0), (300001, "12345 6789 !!!", "en", "s", 14), (300002, None, None, None, None), (None, "the of and there is " * 3, "en", "s", 60)]
    planted += [(400000 + i, " ".join(rng.sample(long[20 + i].text.split(), 120)) + " " + passage, "en", "s", 900) for i in range(5)]
    rows = docs.unionByName(spark.createDataFrame(planted, docs.schema))
    out = {"input": rows}
    for name, f in P.STAGES:
        f(spark, rows, SF).write.parquet(str(at / name))
        out[name] = rows = spark.read.parquet(str(at / name))
    return {k: v.collect() for k, v in out.items()}


def ids(rows):
    return {r.doc_id for r in rows}


def test_order_and_columns(stages):
    assert [n for n, _ in P.STAGES] == ["language_id", "quality", "near_duplicates", "substring_dedup", "packing"]
    for n in ("language_id", "quality", "near_duplicates", "substring_dedup"):
        assert set(stages[n][0].asDict()) == set(P.COLUMNS)


def test_rejections(stages):
    lang = ids(stages["language_id"])
    assert not lang & {300000, 300001, 300002} and len(lang) >= 0.97 * len(ids(stages["input"]))


def test_clean_documents_stay(stages, spark):
    good = {r.doc_id for r in spark.read.parquet(f"{SF}/labels.parquet").where("quality = 1").collect()}
    kept = ids(stages["quality"])
    assert len(good & kept) >= 0.98 * len(good)
    bad = {r.doc_id for r in spark.read.parquet(f"{SF}/labels.parquet").where("quality = 0").collect()}
    assert len(bad - kept) >= 0.8 * len(bad)


def test_copies_go(stages):
    kept, before = ids(stages["near_duplicates"]), ids(stages["quality"])
    assert not kept & set(range(100000, 100019)) and len(kept & set(range(200000, 200019))) <= 2
    texts = [r.text for r in stages["near_duplicates"]]
    assert len(texts) == len(set(texts)) and kept <= before
    assert None in kept


def test_copies_without_doc_id_go(spark):
    """Rows without doc_id go where a row with one has their text or nearly so; of those that
    are alike among themselves one stays."""
    words = lambda c: " ".join(f"{c}{i}" for i in range(60))
    texts = [(None, words("a")), (7, words("a")), (None, words("a") + " end"), (None, words("b")), (None, words("b")), (None, words("b") + " end"), (None, words("c")), (9, words("d"))]
    rows = spark.createDataFrame([(i, t, "en", f"s{k}", len(t)) for k, (i, t) in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    got = dict(P.STAGES)["near_duplicates"](spark, rows, SF).collect()
    assert sorted(r.doc_id for r in got if r.doc_id is not None) == [7, 9]
    assert sorted(r.text[:2] for r in got if r.doc_id is None) == ["b0", "c0"]
    assert {r.source for r in got} < {"s1", "s3", "s5", "s6", "s7"} and all(r.n_chars == len(r.text) for r in got)


def test_passages_go(stages):
    carriers = [r for r in stages["near_duplicates"] if r.doc_id is not None and 400000 <= r.doc_id < 400005]
    passage = " ".join(carriers[0].text.split()[-30:])
    before, after = (sum(passage in " ".join((r.text or "").split()) for r in stages[n]) for n in ("near_duplicates", "substring_dedup"))
    assert len(carriers) >= 3 and before >= len(carriers) and after <= 1


def test_packed(stages):
    bins = {}
    for r in stages["packing"]:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in bins.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 2048
    assert ids(stages["packing"]) == ids(stages["substring_dedup"])


def test_components_of_few_links_in_one_task(spark, monkeypatch):
    from clearbound.llm import common

    links = [(7, 3), (3, 9), (9, 7), (20, 21), (22, 21), (-5, 40), (40, 41), (41, 42), (6, 6)]
    df = spark.createDataFrame(links, "a long, b long")
    want = [(-5, -5), (3, 3), (7, 3), (9, 3), (20, 20), (21, 20), (22, 20), (40, -5), (41, -5), (42, -5)]
    stages = []
    real = common.cut
    monkeypatch.setattr(common, "cut", lambda x: stages.append(1) or real(x))
    assert sorted(map(tuple, common.components(df).collect())) == sorted(want)
    assert len(stages) == 2
    assert common.components(df.where("false")).count() == 0
    monkeypatch.setattr(common, "FEW_LINKS", -1)
    assert sorted(map(tuple, common.components(df).collect())) == sorted(want)
