"""Stage 1 of the audit: k-gram overlap by an inverted index, with pruned, sketched and
brute-force forms, containment and within-pool dedup."""

from __future__ import annotations

import hashlib
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as X
from ..sources.tables import spread, stored
from . import scan
from .embed import normalize_text
from .scan import WORDS, distinct_grams

#: Characters of an eval side up to which its postings are joined by broadcast; a larger one
#: is scanned in blocks, so that pairs that are not asked for are never rows.
BROADCAST_CHARS = 1_000_000


def gram_sets(df: DataFrame, k: int = 5, keep: tuple[str, ...] = ("id",)) -> DataFrame:
    """keep, grams (distinct 64-bit hashes) and n. One Arrow pass: as expressions (see
    functions.text.shingle_hashes, which SQL users get) lambdas over arrays are interpreted
    and took four times as long."""
    keep = tuple(keep)

    def run(batches):
        memory: dict[str, int] = {}
        for b in batches:
            for lo in range(0, b.num_rows, 512):
                part = b.slice(lo, 512)
                if len(memory) > 500_000:
                    memory.clear()
                sets = [distinct_grams(WORDS(normalize_text(t or "")), k, memory) for t in part.column(len(keep)).to_pylist()]
                n = np.fromiter(map(len, sets), np.int32, len(sets))
                flat = pa.array(np.concatenate(sets) if sets else np.zeros(0, np.int64))
                grams = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(n)].astype(np.int32)), flat)
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), grams, pa.array(n)], [*keep, "grams", "n"])

    rows = df.select(*keep, "text")
    rows = rows if df.isStreaming else spread(rows)
    kinds = ", ".join(f"`{c}` {t}" for c, t in rows.dtypes[: len(keep)])
    return rows.mapInArrow(run, f"{kinds}, grams array<bigint>, n int")


def _postings(sets: DataFrame, side: str, keys: tuple[str, ...]) -> DataFrame:
    return sets.select(*(F.col(c).alias(f"{side}_{c}") for c in keys), F.col("n").alias(f"{side}_n"), F.explode("grams").alias("gram"))


def overlaps(train: DataFrame, evals: DataFrame, k: int = 5, keys: tuple[str, ...] = ("id",)) -> DataFrame:
    """t_<keys>, e_id, inter, t_n, e_n of every pair that shares a gram. The eval side's
    postings are broadcast while small, so only counted pairs are shuffled."""
    return _joined(train, evals, k, keys, is_small(evals))


def is_small(evals: DataFrame) -> bool:
    return (evals.agg(F.sum(F.length("text"))).first()[0] or 0) <= BROADCAST_CHARS


def _joined(train: DataFrame, evals: DataFrame, k: int, keys: tuple[str, ...], small: bool) -> DataFrame:
    t = _postings(gram_sets(train, k, keys), "t", keys)
    e = _postings(gram_sets(evals, k), "e", ("id",))
    e = F.broadcast(e) if small else e
    by = [*(f"t_{c}" for c in keys), "e_id"]
    return t.join(e, "gram").groupBy(*by).agg(F.count(F.lit(1)).alias("inter"), F.first("t_n").alias("t_n"), F.first("e_n").alias("e_n"))


def _jaccard() -> Column:
    return F.col("inter") / (F.col("t_n") + F.col("e_n") - F.col("inter"))


def _scanned(train: DataFrame, evals: DataFrame, k: int, keys: tuple[str, ...], score, tau: float, name: str, *least: float) -> DataFrame:
    """t_<keys>, e_id, inter and the score of the pairs that reach tau."""

    def work(s, blocks):
        for b in blocks:
            for row, place, inter, v in scan.lexical_pairs(s, b, (score, tau, *least)):
                yield row, (b.ids[place], inter, v)

    f = scan.Features(k=k)
    kinds = dict(train.dtypes)
    schema = ", ".join(f"t_{c} {kinds[c]}" for c in keys) + f", e_id bigint, inter bigint, {name} double"
    return scan.run(train, scan.blocks(evals, f, scan.EVAL_BYTES), f, work, schema, keys)


def pairs(train: DataFrame, evals: DataFrame, k: int = 5, tau: float = 0.4, keys: tuple[str, ...] = ("id",)) -> DataFrame:
    """Pairs of Jaccard at least tau (inclusive)."""
    if not is_small(evals):
        return _scanned(train, evals, k, keys, lambda inter, t, e: inter / (t + e - inter), tau, "jaccard", tau)
    return _joined(train, evals, k, keys, True).withColumn("jaccard", _jaccard()).where(F.col("jaccard") >= tau - 1e-9).drop("t_n", "e_n")


def best(train: DataFrame, evals: DataFrame, k: int = 5) -> DataFrame:
    """t_id, best_e, j_max: the largest overlap of each train record, 0 if it has none;
    ties go to the smallest eval id."""

    def work(s, blocks):
        top = scan.BestLexical(s)
        for b in blocks:
            top.step(b)
        yield None, top.rows()

    f = scan.Features(k=k)
    return scan.run(train, scan.blocks(evals, f, scan.EVAL_BYTES), f, work, "t_id bigint, best_e bigint, j_max double")


def top(train: DataFrame, evals: DataFrame, most: int, k: int = 5) -> DataFrame:
    """t_id, e_id, rank, jaccard: the ``most`` largest overlaps of each train record; those
    equal to nine digits are ties, which go to smaller eval ids."""

    def work(s, blocks):
        found = scan.TopLexical(s, most)
        for b in blocks:
            found.step(b)
        row, e, rank, j = found.rows()
        yield row, (e, rank.astype(np.int32), j)

    f = scan.Features(k=k)
    return scan.run(train, scan.blocks(evals, f, scan.EVAL_BYTES), f, work, "t_id bigint, e_id bigint, rank int, jaccard double")


def containment(train: DataFrame, evals: DataFrame, k: int = 5, tau: float = 0.8) -> DataFrame:
    """Extension for a short text inside a long one: shared grams over the eval's grams."""
    if not is_small(evals):
        return _scanned(train, evals, k, ("id",), lambda inter, t, e: inter / e, tau, "containment")
    return _joined(train, evals, k, ("id",), True).withColumn("containment", F.col("inter") / F.col("e_n")).where(F.col("containment") >= tau - 1e-9).select("t_id", "e_id", "inter", "containment")


def pairs_brute(train: DataFrame, evals: DataFrame, k: int = 5, tau: float = 0.4) -> DataFrame:
    """Every pair compared: for tests on small inputs."""
    t = gram_sets(train, k).select(F.col("id").alias("t_id"), F.col("grams").alias("a"))
    e = gram_sets(evals, k).select(F.col("id").alias("e_id"), F.col("grams").alias("b"))
    out = t.crossJoin(e).withColumn("inter", F.size(F.array_intersect("a", "b"))).withColumn("jaccard", X.jaccard(F.col("a"), F.col("b")))
    return out.where(F.col("jaccard") >= tau - 1e-9).select("t_id", "e_id", F.col("inter").cast("long").alias("inter"), "jaccard")


def _prefixes(sets: DataFrame, tau: float, side: str) -> DataFrame:
    """Each set's rarest grams, as many as a partner at tau must share one of: n - ceil(tau n) + 1."""
    need = F.col("n") - F.ceil(F.col("n") * F.lit(tau) - 1e-9) + 1
    return sets.select(F.col("id").alias(f"{side}_id"), F.col("n").alias(f"{side}_n"), F.explode(F.slice("ranked", F.lit(1), F.greatest(need, F.lit(1)).cast("int"))).alias("gram"))


def _ranked(sets: DataFrame, counts: DataFrame) -> DataFrame:
    """Grams of each set from the rarest to the commonest: one order for both sides."""
    g = sets.select("id", "n", F.explode("grams").alias("gram")).join(counts, "gram")
    return g.groupBy("id", "n").agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "gram"))), lambda s: s["gram"]).alias("ranked"))


def pairs_pruned(train: DataFrame, evals: DataFrame, k: int = 5, tau: float = 0.4) -> DataFrame:
    """As ``pairs`` without loss, for two large sides: candidates share one of each side's
    rarest grams and pass the length filter, then are counted exactly. collect_list is
    of one record's grams, so bounded by its length."""
    a, b = gram_sets(train, k), gram_sets(evals, k)
    counts = a.select(F.explode("grams").alias("gram")).unionAll(b.select(F.explode("grams").alias("gram"))).groupBy("gram").agg(F.count(F.lit(1)).alias("c"))
    t, e = _prefixes(_ranked(a, counts), tau, "t"), _prefixes(_ranked(b, counts), tau, "e")
    fits = F.least("t_n", "e_n") >= F.greatest("t_n", "e_n") * F.lit(tau) - 1e-9
    cand = t.join(e, "gram").where(fits).select("t_id", "e_id").distinct()
    full = cand.join(a.select(F.col("id").alias("t_id"), F.col("grams").alias("ga")), "t_id").join(b.select(F.col("id").alias("e_id"), F.col("grams").alias("gb")), "e_id")
    out = full.withColumn("inter", F.size(F.array_intersect("ga", "gb")).cast("long")).withColumn("jaccard", X.jaccard(F.col("ga"), F.col("gb")))
    return out.where(F.col("jaccard") >= tau - 1e-9).select("t_id", "e_id", "inter", "jaccard")


def pairs_minhash(train: DataFrame, evals: DataFrame, k: int = 5, tau: float = 0.4, bands: int = 40, rows: int = 2) -> DataFrame:
    """Extension for two very large sides: minima of seeded hashes banded, candidates
    verified exactly. Recall is measured against ``pairs``."""

    def signed(sets: DataFrame, side: str) -> DataFrame:
        def least(seed: int) -> Column:
            return F.array_min(F.transform("grams", lambda g: F.xxhash64(g, F.lit(seed))))

        band = lambda b: F.xxhash64(F.lit(b), *(least(b * rows + r) for r in range(rows)))
        return sets.where("n > 0").select(F.col("id").alias(f"{side}_id"), F.explode(F.array(*(band(b) for b in range(bands)))).alias("band"))

    a, b = gram_sets(train, k), gram_sets(evals, k)
    cand = signed(a, "t").join(signed(b, "e"), "band").select("t_id", "e_id").distinct()
    full = cand.join(a.select(F.col("id").alias("t_id"), F.col("grams").alias("ga")), "t_id").join(b.select(F.col("id").alias("e_id"), F.col("grams").alias("gb")), "e_id")
    out = full.withColumn("inter", F.size(F.array_intersect("ga", "gb")).cast("long")).withColumn("jaccard", X.jaccard(F.col("ga"), F.col("gb")))
    return out.where(F.col("jaccard") >= tau - 1e-9).select("t_id", "e_id", "inter", "jaccard")


def dedup_exact(df: DataFrame) -> DataFrame:
    """id, kept: the smallest id of each text stays. Grouped by a 128-bit digest."""
    first = Window.partitionBy(F.md5("text")).orderBy("id")
    return df.select("id", (F.row_number().over(first) == 1).alias("kept"))


def _each_gram(df: DataFrame, k: int, flat: bool) -> DataFrame:
    """(id, n, gram) of each gram of a record, or (id, n, form) with a digest of its grams; none
    of a record without grams."""

    def run(batches):
        memory = scan.Hashes()
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                if len(memory) > 500_000:
                    memory.clear()
                sets = scan.gram_sets([WORDS(normalize_text(t or "")) for t in part.column(1).to_pylist()], k, memory)
                n = np.fromiter(map(len, sets), np.int32, len(sets))
                ids = part.column(0).to_numpy(zero_copy_only=False)
                if flat:
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, n)), pa.array(np.repeat(n, n)), pa.array(np.concatenate(sets))], ["id", "n", "gram"])
                else:
                    some = np.flatnonzero(n)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(n[some]), pa.array([hashlib.md5(sets[i].tobytes()).digest() for i in some], pa.binary())], ["id", "n", "form"])

    return spread(df.select("id", "text")).mapInArrow(run, "id bigint, n int, " + ("gram bigint" if flat else "form binary"))


def _overlapping(df: DataFrame, k: int, tau: float) -> DataFrame:
    """Pairs t_id > e_id of a pool with itself from tau on. A gram that no other record has is
    sent once and no further; a record of which those alone fill the prefix that a partner must
    share a gram of is in no pair, and goes no further either. collect_list is of one record's grams."""
    each = _each_gram(df, k, True).withColumn("c", F.count(F.lit(1)).over(Window.partitionBy("gram"))).where("c > 1")
    need = F.col("n") - F.ceil(F.col("n") * F.lit(tau) - 1e-9) + 1
    sets = each.groupBy("id", "n").agg(F.sort_array(F.collect_list(F.struct("c", "gram")))["gram"].alias("grams")).withColumn("lead", (need - F.col("n") + F.size("grams")).cast("int"))
    sets = stored(sets.where("lead > 0"))
    side = lambda x: sets.select(F.col("id").alias(f"{x}_id"), F.col("n").alias(f"{x}_n"), F.explode(F.expr("slice(grams, 1, lead)")).alias("gram"))
    fits = (F.least("t_n", "e_n") >= F.greatest("t_n", "e_n") * F.lit(tau) - 1e-9) & (F.col("t_id") > F.col("e_id"))
    cand = side("t").join(side("e"), "gram").where(fits).select("t_id", "e_id").distinct()
    full = cand.join(sets.select(F.col("id").alias("t_id"), F.col("n").alias("t_n"), F.col("grams").alias("ga")), "t_id").join(sets.select(F.col("id").alias("e_id"), F.col("n").alias("e_n"), F.col("grams").alias("gb")), "e_id")
    out = full.withColumn("inter", F.size(F.array_intersect("ga", "gb")).cast("long"))
    return out.where(_jaccard() >= tau - 1e-9).select("t_id", "e_id")


def dedup_lexical(df: DataFrame, k: int = 5, tau: float = 0.4) -> DataFrame:
    """id, kept: a record goes if one of smaller id overlaps it. Records of equal gram sets
    are one class, whose smallest id stands for it in the pruned join of the pool with
    itself; so copies make no pairs. A record without grams stays."""
    forms = stored(_each_gram(df, k, False))
    classes = forms.groupBy("form").agg(F.min("id").alias("first"))
    later = _overlapping(df.join(classes.select(F.col("first").alias("id")), "id", "left_semi"), k, tau).select(F.col("t_id").alias("id"))
    copies = forms.join(classes, "form").where(F.col("id") != F.col("first")).select("id")
    gone = later.unionByName(copies).distinct().withColumn("hit", F.lit(True))
    return df.select("id").join(gone, "id", "left").select("id", F.col("hit").isNull().alias("kept"))


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
