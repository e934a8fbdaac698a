"""Candidates, judged precision, removal, certification and the audit's reports."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as X
from ..sources.tables import stored
from . import lexical, scan, semantic
from .embed import CharGrams

TAU_J, TAU_C = 0.4, 0.85
#: Thresholds of the sweeps.
SWEEP_J, SWEEP_C = (0.3, 0.4, 0.5), (0.80, 0.85, 0.90)


# -- stage 1 and 2 together


def best_scores(train: DataFrame, evals: DataFrame, embedder: CharGrams, k: int = 5, keep: tuple[str, ...] = (), taus: tuple[float, float] | None = None, whole: bool = True) -> DataFrame:
    """t_id, best_lex, j_max, best_sem, c_max for each train record; the columns ``keep`` of
    them stored. With ``taus``, thresholds of both stages, a score below its own is null; if
    ``whole``, only where the other stage does not flag the record either."""
    tau_j, tau_c = taus or (0.0, None)

    def work(s, blocks):
        lex, sem = scan.BestLexical(s, tau_j), scan.BestCosine(s, tau_c)
        for b in blocks:
            lex.step(b)
            sem.step(b)
        out = [*lex.rows(), *sem.rows()]
        if taus and whole:
            no_lex, no_sem = (out[c].is_null().to_numpy(False) for c in (0, 2))
            asked = [(0, scan.BestLexical, np.flatnonzero(no_lex & ~no_sem)), (2, scan.BestCosine, np.flatnonzero(no_sem & ~no_lex))]
            again = [(c, at, kind(scan.Slice([s.values[i] for i in at.tolist()], f, s.memory))) for c, kind, at in asked if at.size]
            for b in blocks if again else ():
                for _, _, x in again:
                    x.step(b)
            for c, at, x in again:
                place = np.zeros(s.size, bool)
                place[at] = True
                for k, own in enumerate(x.rows()):
                    out[c + k] = pc.replace_with_mask(out[c + k], pa.array(place), own)
        yield None, out

    f = scan.Features(k=k, embedder=embedder, bounded=taus is not None)
    shared = scan.blocks(evals, f, scan.EVAL_BYTES)
    best = scan.run(train, shared, f, work, "t_id bigint, best_lex bigint, j_max double, best_sem bigint, c_max double")
    return stored(best.select(*keep), shared) if keep else best


def candidates(best: DataFrame, rule: str = "union", tau_j: float = TAU_J, tau_c: float = TAU_C) -> DataFrame:
    """Adds flag_lex and flag_sem, keeps what the rule takes: union, semantic or lexical."""
    reaches = lambda c, tau: F.coalesce(F.col(c) >= tau - 1e-9, F.lit(False))
    out = best.withColumn("flag_lex", reaches("j_max", tau_j)).withColumn("flag_sem", reaches("c_max", tau_c))
    keep = {"union": F.col("flag_lex") | F.col("flag_sem"), "semantic": F.col("flag_sem"), "lexical": F.col("flag_lex")}[rule]
    return out.where(keep)


def top_match(cands: DataFrame) -> DataFrame:
    """(t_id, e_id): the semantic best partner, or the lexical one of a record that only stage 1 flags."""
    return cands.select("t_id", F.when(F.col("flag_sem"), F.col("best_sem")).otherwise(F.col("best_lex")).alias("e_id"))


def all_pairs(train: DataFrame, evals: DataFrame, embedder: CharGrams, tau_j: float = TAU_J, tau_c: float = TAU_C) -> DataFrame:
    """t_id, e_id, jaccard, cosine of every pair that either stage flags, with both flags.
    The score of a stage that does not flag the pair is null."""
    lex = lexical.pairs(train, evals, tau=tau_j).select("t_id", "e_id", "jaccard")
    sem = semantic.pairs(train, evals, embedder, tau_c)
    out = lex.join(sem, ["t_id", "e_id"], "full")
    return out.withColumn("stage1", F.col("jaccard").isNotNull()).withColumn("stage2", F.col("cosine").isNotNull())


# -- stage 3


@dataclass(frozen=True)
class RuleJudge:
    """Stand-in for a language-model judge: close duplicate if, with digits masked, enough
    token 3-grams of the smaller text are in the other and the lengths are alike. Digit
    masking makes numeric variations duplicates. Its accuracy is measured, not claimed."""

    theta: float = 0.5
    length: float = 0.5

    def columns(self, a: Column, b: Column) -> dict[str, Column]:
        masked = lambda x: X.tokens(F.regexp_replace(X.normalize(x), r"[0-9]+", "0"))

        def body(s: dict[str, Column]) -> Column:
            small, longest = F.least(F.size(s["ga"]), F.size(s["gb"])), F.greatest(s["na"], s["nb"])
            return F.struct(
                F.when(small > 0, F.size(F.array_intersect(s["ga"], s["gb"])) / small).otherwise(F.lit(0.0)).alias("contained"),
                F.when(longest > 0, F.least(s["na"], s["nb"]) / longest).otherwise(F.lit(1.0)).alias("length_ratio"),
            )

        one = lambda x, g, n: X.let(masked(x), lambda w: F.struct(X.shingles(w, 3).alias(g), F.size(w).alias(n)))
        both = X.let(F.struct(one(a, "ga", "na").alias("x"), one(b, "gb", "nb").alias("y")), lambda s: body({"ga": s["x"]["ga"], "na": s["x"]["na"], "gb": s["y"]["gb"], "nb": s["y"]["nb"]}))
        return {"_judged": both}

    def judge(self, pairs: DataFrame) -> DataFrame:
        """pairs: t_text, e_text and others. Adds contained, length_ratio and label."""
        out = pairs.withColumns(self.columns(F.col("t_text"), F.col("e_text"))).select("*", "_judged.*").drop("_judged")
        close = (F.col("contained") >= self.theta - 1e-9) & (F.col("length_ratio") >= self.length - 1e-9)
        return out.withColumn("label", F.when(close, "close_dup").otherwise("topic_neighbor"))


@dataclass(frozen=True)
class ReplayJudge:
    """Verdicts stored before: t_digest, e_digest, label. A pair without one is an error row."""

    archive: DataFrame

    def judge(self, pairs: DataFrame) -> DataFrame:
        keyed = pairs.withColumn("t_digest", F.sha2("t_text", 256)).withColumn("e_digest", F.sha2("e_text", 256))
        return keyed.join(self.archive.dropDuplicates(["t_digest", "e_digest"]), ["t_digest", "e_digest"], "left").withColumn("label", F.coalesce("label", F.lit("error")))


#: Templates of a judge outside, by id. Verdicts carry the id; a changed text is a new id.
TEMPLATES = {
    "pair-v1": "Compare two problem statements.\nFirst: {a}\nSecond: {b}\nReply close_dup if one restates the other or only changes its numbers, topic_neighbor if they merely share a subject.",
    "answer-v1": "Reference answer: {a}\nSubmitted answer: {b}\nIs the submitted answer equivalent, up to rounding and notation? Reply with the single word YES or NO.",
}


@dataclass(frozen=True)
class EndpointJudge:
    """Adapter to judges outside: a chain of callables (t_text, e_text) -> label tried in
    turn, ``retries`` each, at most ``workers`` calls at once. Results should be written
    before use, so that a recomputed plan does not ask again."""

    chain: tuple[tuple[str, Callable[[str, str], str]], ...]
    template: str = "pair-v1"
    workers: int = 4
    retries: int = 2

    def judge(self, pairs: DataFrame) -> DataFrame:
        chain, retries, template = self.chain, self.retries, self.template

        def run(frames):
            for f in frames:
                labels, models = [], []
                for a, b in zip(f["t_text"], f["e_text"], strict=True):
                    label, by = "error", None
                    for name, ask in chain:
                        for _ in range(retries):
                            try:
                                label, by = ask(a, b), name
                                break
                            except Exception:  # noqa: BLE001  an outside judge may fail in any way
                                label = "error"
                        if by:
                            break
                    labels.append(label)
                    models.append(by)
                yield f.assign(label=labels, judge=models, template=template)

        kinds = ", ".join(f"`{n}` {t}" for n, t in pairs.dtypes)
        return pairs.repartition(self.workers).mapInPandas(run, f"{kinds}, label string, judge string, template string")


def with_texts(pairs: DataFrame, train: DataFrame, evals: DataFrame) -> DataFrame:
    t = train.select(F.col("id").alias("t_id"), F.col("text").alias("t_text"))
    e = evals.select(F.col("id").alias("e_id"), F.col("text").alias("e_text"))
    return pairs.join(t, "t_id").join(e, "e_id")


def judged(pairs: DataFrame, train: DataFrame, evals: DataFrame, judge=None) -> DataFrame:
    return (judge or RuleJudge()).judge(with_texts(pairs, train, evals)).drop("t_text", "e_text")


def _pairs_of(s, b, tau_j: float, tau_c: float, scores: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, places in the block and both scores of the pairs that either stage flags; the
    score of a stage that does not is nan. ``scores`` as for ``scan.near_pairs``."""
    jaccard, n, nothing = lambda inter, t, e: inter / (t + e - inter), len(b.ids), (np.zeros(0, np.int64), np.zeros(0))
    lex = [np.concatenate(x) for x in zip(nothing, *((r * n + p, v) for r, p, _, v in scan.lexical_pairs(s, b, (jaccard, tau_j, tau_j))), strict=True)]
    sem = [np.concatenate(x) for x in zip(nothing, *((r * n + p, v) for r, p, v in scan.near_pairs(s, b, tau_c, scores)), strict=True)]
    cells = np.union1d(lex[0], sem[0])
    out = np.full((2, cells.size), np.nan)
    for k, (cell, v) in enumerate((lex, sem)):
        out[k, np.searchsorted(cells, cell)] = v
    return cells // n, cells % n, out


def _close(judge: RuleJudge, contained: np.ndarray, ratio: np.ndarray) -> np.ndarray:
    return (contained >= judge.theta - 1e-9) & (ratio >= judge.length - 1e-9)


def verdicts(train: DataFrame, evals: DataFrame, embedder: CharGrams, judge: RuleJudge | None = None, tau_j: float = TAU_J, tau_c: float = TAU_C, keep: tuple[str, ...] = ()) -> DataFrame:
    """``judged`` of ``all_pairs``: with the rule judge in one scan, which takes texts to no
    pair; with another judge as those two. The columns ``keep`` of them stored."""
    judge = judge or RuleJudge()
    if not isinstance(judge, RuleJudge):
        out = judged(all_pairs(train, evals, embedder, tau_j, tau_c), train, evals, judge)
        return stored(out.select(*keep)) if keep else out

    def work(s, blocks):
        for b in blocks:
            row, place, scores = _pairs_of(s, b, tau_j, tau_c)
            if not row.size:
                continue
            none = np.isnan(scores)
            contained, ratio = scan.judge(s, b, row, place)
            close = _close(judge, contained, ratio)
            label = pa.DictionaryArray.from_arrays(pa.array(close.astype(np.int8)), pa.array(["topic_neighbor", "close_dup"])).cast(pa.string())
            yield row, (b.ids[place], pa.array(scores[0], mask=none[0]), pa.array(scores[1], mask=none[1]), ~none[0], ~none[1], contained, ratio, label)

    f = scan.Features(k=5, embedder=embedder, masked=True, bounded=True)
    schema = "t_id bigint, e_id bigint, jaccard double, cosine double, stage1 boolean, stage2 boolean, contained double, length_ratio double, label string"
    shared = scan.blocks(evals, f, scan.EVAL_BYTES)
    out = scan.run(train, shared, f, work, schema)
    return stored(out.select(*keep), shared) if keep else out


def eval_hits(train: DataFrame, evals: DataFrame, embedder: CharGrams, tau_j: float = TAU_J, tau_c: float = TAU_C) -> DataFrame:
    """e_id, stage1 of the eval records that either stage flags with a train record, once or
    more; no pair leaves the task and none is judged."""

    def work(s, blocks):
        for b in blocks:
            _, place, scores = _pairs_of(s, b, tau_j, tau_c, False)
            hit, lex = np.unique(place), np.zeros(b.ids.size, bool)
            lex[place[~np.isnan(scores[0])]] = True
            yield np.zeros(hit.size, np.int64), (b.ids[hit], lex[hit])

    f = scan.Features(k=5, embedder=embedder, bounded=True)
    return scan.run(train, scan.blocks(evals, f, scan.EVAL_BYTES), f, work, "t_id bigint, e_id bigint, stage1 boolean").drop("t_id")


def pair_counts(train: DataFrame, evals: DataFrame, embedder: CharGrams, split: str = "lang", judge: RuleJudge | None = None, tau_j: float = TAU_J, tau_c: float = TAU_C) -> DataFrame:
    """pool, split, s1, s2, s3: pairs of each train pool and eval split that the stages flag
    and the judge calls duplicates. They are counted where they are found. train has a
    column pool, evals one that ``split`` names."""
    judge = judge or RuleJudge()

    def work(s, blocks):
        pools: dict = {}
        pool = np.array([pools.setdefault(p, len(pools)) for p in s.keys.column(1).to_pylist()], np.int64)
        splits: dict = {}
        n: dict[tuple[int, int], np.ndarray] = {}
        for b in blocks:
            split = np.array([splits.setdefault(x, len(splits)) for x in b.labels], np.int64)
            row, place, scores = _pairs_of(s, b, tau_j, tau_c, False)
            if not row.size:
                continue
            flags = np.vstack([~np.isnan(scores), _close(judge, *scan.judge(s, b, row, place))])
            cells, at = np.unique(pool[row] * len(splits) + split[place], return_inverse=True)
            for k, cell in enumerate(cells.tolist()):
                key = divmod(cell, len(splits))
                n[key] = n.get(key, 0) + flags[:, at == k].sum(1)
        first = {p: i for i, p in reversed(list(enumerate(pool.tolist())))}
        names = list(splits)
        counts = np.array([*n.values()], np.int64).reshape(-1, 3)
        yield np.array([first[p] for p, _ in n], np.int64), (pa.array([names[x] for _, x in n], pa.string()), *counts.T)

    f = scan.Features(k=5, embedder=embedder, masked=True, bounded=True)
    each = scan.run(train, scan.blocks(evals, f, scan.EVAL_BYTES, split), f, work, "t_id bigint, pool string, split string, s1 bigint, s2 bigint, s3 bigint", ("id", "pool"))
    return each.groupBy("pool", "split").agg(*(F.sum(c).alias(c) for c in ("s1", "s2", "s3")))


def meetings(train: DataFrame, evals: DataFrame, embedder: CharGrams, tau_j: float = TAU_J, tau_c: float = TAU_C) -> DataFrame:
    """One row: pairs that share a gram, pairs of stage 1 and pairs of stage 2."""

    def work(s, blocks):
        n = np.zeros(3, np.int64)
        for b in blocks:
            for r, c, _, j in scan.jaccards(s, b):
                both = s.classes.size[r] * b.classes.size[c]
                n[:2] += both.sum(), both[j >= tau_j - 1e-9].sum()
            n[2] += sum(r.size for r, *_ in scan.near_pairs(s, b, tau_c, False))
        yield [0], ([n[0]], [n[1]], [n[2]])

    f = scan.Features(k=5, embedder=embedder, bounded=True)
    each = scan.run(train, scan.blocks(evals, f, scan.EVAL_BYTES), f, work, "t_id bigint, shared bigint, s1 bigint, s2 bigint")
    return each.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(f"{c}_pairs") for c in ("shared", "s1", "s2")))


# -- removal and certification


def remove(train: DataFrame, verdicts: DataFrame, removal: str = "close_dup") -> DataFrame:
    """The pool without judged duplicates, or (all_candidates) without any candidate."""
    gone = verdicts if removal == "all_candidates" else verdicts.where("label = 'close_dup'")
    return train.join(gone.select(F.col("t_id").alias("id")).distinct(), "id", "left_anti")


def certificate(train: DataFrame, evals: DataFrame, embedder: CharGrams, judge: RuleJudge | None = None, tau_j: float = TAU_J, tau_c: float = TAU_C, rule: str = "union", removal: str = "close_dup") -> DataFrame:
    """One row: what was audited and how, and what a second audit of the released pool finds."""
    found = verdicts(train, evals, embedder, judge, tau_j, tau_c, ("t_id", "stage1", "stage2", "label"))
    released = remove(train, found, removal)
    again = verdicts(released, evals, embedder, judge, tau_j, tau_c)
    count = lambda cond, name: F.coalesce(F.sum(F.when(cond, 1).otherwise(0)), F.lit(0)).cast("long").alias(name)
    before = found.agg(count(F.col("stage1"), "stage1_pairs"), count(F.col("stage2"), "stage2_pairs"), count(F.col("label") == "close_dup", "close_dup_pairs"))
    after = again.agg(count(F.col("label") == "close_dup", "remaining_close_dup"), count(F.col("label") != "close_dup", "remaining_neighbor"))
    sizes = train.agg(F.count(F.lit(1)).alias("pool_size")).crossJoin(released.agg(F.count(F.lit(1)).alias("released_size"), F.sum(F.conv(F.substring(F.md5(F.col("id").cast("string")), 1, 8), 16, 10).cast("long")).alias("released_digest")))
    out = sizes.crossJoin(before).crossJoin(after)  # four rows of one
    return stamp(out, embedder.name, "rule", tau_j, tau_c, rule, removal).withColumn("passed", F.col("remaining_close_dup") == 0).withColumn("strict_passed", (F.col("remaining_close_dup") + F.col("remaining_neighbor")) == 0)


def stamp(df: DataFrame, embedder: str, judge: str, tau_j: float, tau_c: float, rule: str, removal: str, version: str = "1") -> DataFrame:
    """Operating thresholds and versions on every released verdict."""
    return df.withColumns({"tau_j": F.lit(tau_j), "tau_c": F.lit(tau_c), "embedder": F.lit(embedder), "judge": F.lit(judge), "rule": F.lit(rule), "removal": F.lit(removal), "audit_version": F.lit(version)})


def assert_disjoint(cert: DataFrame) -> DataFrame:
    """Fails the job if a close duplicate remains."""
    return cert.withColumn("checked", F.assert_true(F.col("passed"), F.lit("the released pool still holds a close duplicate")).isNull())


def cleanup(train: DataFrame, passes: list[tuple[str, DataFrame, Callable[[DataFrame, DataFrame], DataFrame]]]) -> DataFrame:
    """Ledger of ordered passes (name, eval, finder): how many records each channel flags in
    the pool, by which stage, how many of them an earlier pass had flagged, and what it drops
    that none had. A finder gives t_id, stage1, stage2, once or more for a record."""
    rows, dropped = None, None
    total = train.count()
    for no, (name, ev, find) in enumerate(passes, 1):
        flagged = stored(find(train, ev).groupBy("t_id").agg(F.max("stage1").alias("s1"), F.max("stage2").alias("s2")))
        new = flagged if dropped is None else flagged.join(dropped, "t_id", "left_anti")
        dropped = new if dropped is None else dropped.unionByName(new)
        counts = flagged.agg(F.count(F.lit(1)).alias("flagged"), F.count_if("s1").alias("by_lexical"), F.count_if("s2").alias("by_semantic"))
        both = counts.crossJoin(new.agg(F.count(F.lit(1)).alias("dropped_new")))  # a row each
        row = both.select(F.lit(no).alias("pass_no"), F.lit(name).alias("eval"), "flagged", "by_lexical", "by_semantic", (F.col("flagged") - F.col("dropped_new")).alias("flagged_before"), "dropped_new")
        rows = row if rows is None else rows.unionByName(row)
    so_far = F.sum("dropped_new").over(Window.orderBy("pass_no").rowsBetween(Window.unboundedPreceding, 0))  # a row a pass
    return rows.withColumn("remaining", (F.lit(total) - so_far).cast("long"))


def release_gate(train: DataFrame, flagged: DataFrame, rate: float = 0.01) -> DataFrame:
    """flagged, size, leak_rate, gate ('remove' from the rate on) of a pool against a new eval."""
    n = train.agg(F.count(F.lit(1)).alias("size"))
    f = flagged.select("t_id").distinct().agg(F.count(F.lit(1)).alias("flagged"))
    out = f.crossJoin(n).withColumn("leak_rate", F.when(F.col("size") > 0, F.col("flagged") / F.col("size")).otherwise(0.0))
    return out.withColumn("gate", F.when(F.col("leak_rate") >= rate, "remove").otherwise("keep"))


def removal_diff(train: DataFrame, flagged: DataFrame, rate: float = 0.01) -> DataFrame:
    """id, pool, change ('removed') of the records that a release loses: those that are
    flagged where the gate says remove, else none."""
    hit = flagged.select(F.col("t_id").alias("id")).distinct()
    gate = release_gate(train, flagged, rate).where("gate = 'remove'").select("gate")
    return train.select("id", "pool").join(hit, "id", "left_semi").crossJoin(F.broadcast(gate)).select("id", "pool", F.lit("removed").alias("change"))  # one row or none


# -- reports


def stage_counts(verdicts: DataFrame) -> DataFrame:
    n = lambda c: F.coalesce(F.sum(c.cast("int")), F.lit(0)).cast("long")
    return verdicts.agg(n(F.col("stage1")).alias("s1_pairs"), n(F.col("stage2")).alias("s2_pairs"), n(F.col("label") == "close_dup").alias("s3_pairs"), F.countDistinct(F.when(F.col("stage1") | F.col("stage2"), F.col("t_id"))).alias("records"))


def matrix(verdicts: DataFrame, members: DataFrame, pools: DataFrame) -> DataFrame:
    """Long matrix: each pair counts for every eval split that holds its item, and zero
    cells stay. members: id, eval; pools: id, pool."""
    n = lambda c: F.sum(F.coalesce(c.cast("int"), F.lit(0))).cast("long")
    hit = verdicts.join(pools.select(F.col("id").alias("t_id"), "pool"), "t_id").join(members.select(F.col("id").alias("e_id"), "eval"), "e_id")
    return _grid(hit.groupBy("eval", "pool").agg(n(F.col("stage1")).alias("s1"), n(F.col("stage2")).alias("s2"), n(F.col("label") == "close_dup").alias("s3")), members, pools)


def _grid(cells: DataFrame, members: DataFrame, pools: DataFrame) -> DataFrame:
    grid = members.select("eval").distinct().crossJoin(pools.select("pool").distinct())
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return grid.join(cells, ["eval", "pool"], "left").select("eval", "pool", zero("s1"), zero("s2"), zero("s3"))


def totals(verdicts: DataFrame, members: DataFrame, pools: DataFrame) -> DataFrame:
    """Sum of cells beside the number of unique pairs, for stages 2 and 3, by pool."""
    own = verdicts.join(pools.select(F.col("id").alias("t_id"), "pool"), "t_id")
    n = lambda c: F.sum(F.coalesce(c.cast("int"), F.lit(0))).cast("long")
    unique = own.groupBy("pool").agg(n(F.col("stage2")).alias("s2_unique"), n(F.col("label") == "close_dup").alias("s3_unique"))
    return _totals(matrix(verdicts, members, pools), unique)


def _totals(matrix: DataFrame, unique: DataFrame) -> DataFrame:
    cells = matrix.groupBy("pool").agg(F.sum("s2").alias("s2_cells"), F.sum("s3").alias("s3_cells"))
    return cells.join(unique, "pool", "left").na.fill(0, ["s2_unique", "s3_unique"]).select("pool", "s2_cells", "s2_unique", "s3_cells", "s3_unique")


def counted_matrix(counts: DataFrame, splits: DataFrame, members: DataFrame, pools: DataFrame) -> DataFrame:
    """``matrix`` from ``pair_counts``; splits: split, eval (those that its items are in)."""
    evals = splits.withColumnRenamed("split", "of")
    cells = counts.join(F.broadcast(evals), F.col("split").eqNullSafe(F.col("of"))).groupBy("eval", "pool").agg(*(F.sum(c).alias(c) for c in ("s1", "s2", "s3")))
    return _grid(cells, members, pools)


def counted_totals(counts: DataFrame, splits: DataFrame, members: DataFrame, pools: DataFrame) -> DataFrame:
    """``totals`` from ``pair_counts``."""
    return _totals(counted_matrix(counts, splits, members, pools), counts.groupBy("pool").agg(F.sum("s2").alias("s2_unique"), F.sum("s3").alias("s3_unique")))


BUCKETS = (("[0.85,0.87)", 0.85, 0.87), ("[0.87,0.90)", 0.87, 0.90), ("[0.90,0.95)", 0.90, 0.95), ("[0.95,0.99)", 0.95, 0.99), ("[0.99,1.00]", 0.99, 1.01))


def bucket_of(c: Column) -> Column:
    out = F.lit(None).cast("string")
    for name, lo, hi in reversed(BUCKETS):
        out = F.when((c >= lo - 1e-9) & (c < hi - 1e-9), name).otherwise(out)
    return out


def buckets(verdicts: DataFrame) -> DataFrame:
    """Judged precision by cosine bucket, and in all."""
    v = verdicts.where("stage2").withColumn("bucket", bucket_of(F.col("cosine")))
    out = v.rollup("bucket").agg(F.grouping("bucket").alias("g"), F.count(F.lit(1)).alias("n_pairs"), F.sum((F.col("label") == "close_dup").cast("int")).cast("long").alias("close_dup"))
    return out.select(F.when(F.col("g") == 1, "all").otherwise(F.col("bucket")).alias("bucket"), "n_pairs", "close_dup", (F.col("n_pairs") - F.col("close_dup")).alias("neighbour"), (F.col("close_dup") / F.col("n_pairs")).alias("share"))


def eval_rates(verdicts: DataFrame, members: DataFrame) -> DataFrame:
    v = verdicts.where("stage2").join(members.select(F.col("id").alias("e_id"), "eval"), "e_id")
    return v.groupBy("eval").agg(F.count(F.lit(1)).alias("s2"), F.sum((F.col("label") == "close_dup").cast("int")).cast("long").alias("s3")).withColumn("rate", F.col("s3") / F.col("s2"))


def sweep(best: DataFrame, js=SWEEP_J, cs=SWEEP_C) -> DataFrame:
    """Records flagged at each pair of thresholds, from one pass over the best scores. A score
    that is null reaches none."""
    spark = best.sparkSession
    grid = spark.createDataFrame([(float(j), float(c)) for j in js for c in cs], "j_thr double, c_thr double")
    reaches = lambda c, thr: F.coalesce(F.col(c) >= F.col(thr) - 1e-9, F.lit(False))
    hit = (reaches("j_max", "j_thr") | reaches("c_max", "c_thr")).cast("int")
    return best.crossJoin(F.broadcast(grid)).groupBy("j_thr", "c_thr").agg(F.sum(hit).cast("long").alias("flagged"), F.count(F.lit(1)).alias("records")).withColumn("rate", F.col("flagged") / F.col("records"))


def sweep_single(best: DataFrame, js=SWEEP_J, cs=SWEEP_C) -> DataFrame:
    """Records flagged by one stage alone at each of its thresholds; the other's is null."""
    at = [("lexical", j, None, F.col("j_max") >= j - 1e-9) for j in js] + [("semantic", None, c, F.col("c_max") >= c - 1e-9) for c in cs]
    one = lambda n, j, c, hit: F.struct(F.lit(n).alias("stages"), F.lit(j).cast("double").alias("j_thr"), F.lit(c).cast("double").alias("c_thr"), F.coalesce(hit, F.lit(False)).cast("int").alias("hit"))
    rows = best.select(F.explode(F.array(*(one(*x) for x in at))).alias("r"))
    return rows.groupBy("r.stages", "r.j_thr", "r.c_thr").agg(F.sum("r.hit").cast("long").alias("flagged"), F.count(F.lit(1)).alias("records")).withColumn("rate", F.col("flagged") / F.col("records"))


def single_stage(best: DataFrame, tau_j: float = TAU_J, tau_c: float = TAU_C) -> DataFrame:
    lex, sem = (F.coalesce(c >= tau - 1e-9, F.lit(False)) for c, tau in ((F.col("j_max"), tau_j), (F.col("c_max"), tau_c)))
    rows = best.select(F.explode(F.array(*(F.struct(F.lit(n).alias("stages"), c.cast("int").alias("hit")) for n, c in (("lexical", lex), ("semantic", sem), ("union", lex | sem))))).alias("r"))
    return rows.groupBy("r.stages").agg(F.sum("r.hit").cast("long").alias("flagged"), F.count(F.lit(1)).alias("records")).withColumn("rate", F.col("flagged") / F.col("records"))


def decompose(best: DataFrame) -> DataFrame:
    """Flagged records as exact (J = 1), strong (cosine from .90), weak (.85 to .90), lexical
    only; and how many stage 1 alone would have had."""
    kind = F.when(F.col("j_max") >= 1 - 1e-9, "exact").when(F.col("c_max") >= 0.90 - 1e-9, "strong").when(F.col("c_max") >= TAU_C - 1e-9, "weak").when(F.col("j_max") >= TAU_J - 1e-9, "lexical_only")
    n = best.count()
    return best.withColumn("class", kind).where("class is not null").groupBy("class").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("j_max") >= TAU_J - 1e-9, 1)).alias("seen_by_stage1")).withColumn("rate", F.col("n") / F.lit(n))


def jaccard_histogram(best: DataFrame) -> DataFrame:
    return best.select(F.least(F.floor(F.col("j_max") * 10 + 1e-9), F.lit(10)).cast("int").alias("bin")).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


def embedder_overlap(best1: DataFrame, best2: DataFrame, at=(0.80, 0.85, 0.87, 0.90, 0.95)) -> DataFrame:
    """Candidate sets of two embedders at several cut-offs."""
    both = best1.select("t_id", F.col("c_max").alias("c1")).join(best2.select("t_id", F.col("c_max").alias("c2")), "t_id", "full")
    grid = both.sparkSession.createDataFrame([(float(t),) for t in at], "thr double")
    a, b = F.coalesce(F.col("c1") >= F.col("thr") - 1e-9, F.lit(False)), F.coalesce(F.col("c2") >= F.col("thr") - 1e-9, F.lit(False))
    n = lambda c: F.sum(c.cast("int")).cast("long")
    out = both.crossJoin(F.broadcast(grid)).groupBy("thr").agg(n(a).alias("n1"), n(b).alias("n2"), n(a & b).alias("both"), n(a & ~b).alias("only1"), n(~a & b).alias("only2"))
    union = F.col("both") + F.col("only1") + F.col("only2")
    return out.withColumn("set_jaccard", F.when(union > 0, F.col("both") / union)).withColumn("subset", F.col("only2") == 0)


def coverage(verdicts: DataFrame, members: DataFrame) -> DataFrame:
    """Share of each eval split that some pair hits, by stage 1 and by the union."""
    hits = verdicts.groupBy("e_id").agg(F.max(F.coalesce("stage1", F.lit(False))).alias("s1"))
    rows = members.join(hits.withColumnRenamed("e_id", "id"), "id", "left")
    return rows.groupBy("eval").agg(F.count(F.lit(1)).alias("items"), F.sum(F.coalesce(F.col("s1").cast("int"), F.lit(0))).cast("long").alias("hit_stage1"), F.count("s1").alias("hit_union")).withColumn("coverage", F.col("hit_union") / F.col("items"))


def novelty(evals: DataFrame, channels: list[DataFrame], tau: float = 0.4) -> DataFrame:
    """Eval records and how many no channel overlaps; those that one does are disclosed."""
    hit = lexical.pairs(lexical.union_all([c.select("id", "text") for c in channels]), evals, tau=tau).select(F.col("e_id").alias("id"))
    flags = evals.select("id").join(hit.distinct().withColumn("hit", F.lit(1)), "id", "left")
    return flags.agg(F.count(F.lit(1)).alias("items"), F.count("hit").alias("disclosed")).withColumn("novel", F.col("items") - F.col("disclosed")).withColumn("novel_share", F.col("novel") / F.col("items"))


# -- blind-spot probes


PLANT_KINDS = ("exact", "case", "wrapped", "digits", "drop6", "drop4", "halves", "pairs", "foreign")


def plant(bench: DataFrame) -> DataFrame:
    """id, kind, text, is_dup: copies of each passage changed in known ways, and an unrelated text."""
    words = F.filter(F.split("text", " "), lambda w: w != "")
    drop = lambda n: F.array_join(F.filter(words, lambda w, i: i % n != n - 1), " ")
    half = F.floor(F.size(words) / 2).cast("int")
    swapped = F.array_join(F.concat(F.slice(words, half + 1, F.size(words)), F.slice(words, F.lit(1), half)), " ")
    neighbours = F.array_join(F.transform(words, lambda w, i: F.coalesce(F.get(words, F.when(i % 2 == 0, i + 1).otherwise(i - 1)), w)), " ")
    kinds = {
        "exact": F.col("text"), "case": F.translate(F.regexp_replace("text", " ", "  "), "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), "wrapped": F.concat(F.lit("$\\text{"), F.col("text"), F.lit("}$")), "digits": F.concat(F.col("text"), F.lit(" value 13.7")),
        "drop6": drop(6), "drop4": drop(4), "halves": swapped, "pairs": neighbours, "foreign": F.concat(F.lit("ganz anderer "), F.reverse(F.col("text"))),
    }
    return bench.select("id", F.explode(F.array(*(F.struct(F.lit(k).alias("kind"), c.alias("text"), F.lit(k != "foreign").alias("is_dup")) for k, c in kinds.items()))).alias("p")).select("id", "p.kind", "p.text", "p.is_dup")


def probe_recall(bench: DataFrame, tau_j: float = TAU_J) -> DataFrame:
    """Stage-1 recall by kind of plant, each plant against its own passage."""
    planted = plant(bench)
    own = bench.withColumn("orig", F.concat(F.col("text"), F.lit(""))).select("id", "orig")
    g = lambda c: X.shingles(X.tokens(X.normalize(c)))
    base = F.when(F.col("kind") == "digits", F.concat(F.col("orig"), F.lit(" value 12.5"))).otherwise(F.col("orig"))
    rows = planted.join(own, "id").withColumn("j", X.jaccard(g(F.col("text")), g(base)))
    return rows.groupBy("kind", "is_dup").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("j") >= tau_j - 1e-9).cast("int")).cast("long").alias("hits"), F.avg("j").alias("mean_j"))
