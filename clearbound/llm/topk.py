"""Exact top-k inner products by exhaustive term-at-a-time accumulation.

Queries go round in blocks of bounded size, as sparse rows: a round is run to its end
before the next block leaves the driver. A task turns its candidates into postings (for
each dimension a dense column of weights); each term of a query adds its weighted column
to a dense array of scores. A partition of the candidates gives its best, and the
partitions' best are merged by rank.

Scores are exact: where sums could leave 64 bits a task counts in integers without bound.
A score beyond a long is held at the long's end in the result, and such scores rank by
their values as doubles. Rows that repeat a vec_id are rows of their own: each asks for
itself, and finds the others.
"""

from __future__ import annotations

import math
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, gathered

#: Bytes of query vectors of one round, as doubles: what the driver holds and sends to tasks.
ROUND_BYTES = 32 << 20
#: Candidates scored at once.
BLOCK = 8192
_LONG = 1 << 63


def _whole(vectors: list, scale: int) -> list[np.ndarray | None]:
    """floor(scale * x) as 64-bit integers, as Python integers where one is beyond them, or
    None for a vector that takes no part."""
    out: list[np.ndarray | None] = []
    for v in vectors:
        if v is None or any(x is None for x in v):
            out.append(None)
            continue
        x = np.asarray(v, np.float64)
        if not np.isfinite(x).all():
            out.append(None)
        elif x.size and np.abs(x).max() >= 2.0**62 / scale:
            out.append(np.array([math.floor(Fraction(float(c)) * scale) for c in x], object))
        else:
            out.append(np.floor(scale * x).astype(np.int64))
    return out


def _better(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best: higher scores, ties to smaller ids."""
    if scores.dtype == object:
        return np.array(sorted(range(scores.size), key=lambda i: (-scores[i], ids[i]))[:k], np.int64)
    if scores.size > k:
        edge = np.partition(scores, scores.size - k)[scores.size - k]
        at = np.flatnonzero(scores >= edge)
    else:
        at = np.arange(scores.size)
    return at[np.lexsort((ids[at], -scores[at]))[:k]]


def _double(score: int) -> float:
    try:
        return float(score)
    except OverflowError:
        return math.inf if score > 0 else -math.inf


def _accumulate(queries: list[tuple[int, int, np.ndarray]], k: int, scale: int):
    """Rows (asker, vec_id, score, wide, own) of the k + 1 best of a block for each query:
    one more than asked for, as the query's own row may be among them."""

    def run(batches):
        terms = [(n, q, [(d, w) for d, w in enumerate(v.tolist()) if w], v) for n, q, v in queries]
        for b in gathered(batches, BLOCK):
            for lo in range(0, b.num_rows, BLOCK):
                part = b.slice(lo, BLOCK)
                whole = _whole(part.column("embedding").to_pylist(), scale)
                some = [i for i, v in enumerate(whole) if v is not None]
                if not some:
                    continue
                ids = part.column("vec_id").to_numpy(zero_copy_only=False)[some]
                width = max(whole[i].size for i in some)
                largest = [max((abs(int(whole[i][d])) for i in some if d < whole[i].size), default=0) for d in range(width)] if any(whole[i].dtype == object for i in some) else None
                postings = np.zeros((width, len(some)), np.int64 if largest is None else object)
                for n, i in enumerate(some):
                    postings[: whole[i].size, n] = whole[i]
                if largest is None:
                    largest = np.abs(postings).max(axis=1).tolist()
                unbounded = None
                out: list[list] = [[], [], [], [], []]
                for asker, q, weights, own_vector in terms:
                    narrow = postings.dtype != object and sum(abs(w) * largest[d] for d, w in weights if d < width) < _LONG
                    if not narrow and unbounded is None:
                        unbounded = postings.astype(object)
                    columns = postings if narrow else unbounded
                    scores = np.zeros(len(some), np.int64 if narrow else object)
                    for d, w in weights:
                        if d < width:
                            scores += w * columns[d]
                    best = _better(scores, ids, k + 1)
                    found = scores[best].tolist()
                    out[0] += [asker] * best.size
                    out[1] += ids[best].tolist()
                    out[2] += [max(-_LONG, min(_LONG - 1, s)) for s in found]
                    out[3] += [0.0 if -_LONG <= s < _LONG else _double(s) for s in found]
                    out[4] += [i == q and np.array_equal(whole[some[n]], own_vector) for n, i in zip(best.tolist(), ids[best].tolist(), strict=True)]
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.bool_())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds, strict=True)], ["asker", "vec_id", "score", "wide", "own"])

    return run


def _merged(found: DataFrame, k: int) -> DataFrame:
    """The k best of each asker without its own row (one of them, where equal rows repeat an id)."""
    order = Window.partitionBy("asker").orderBy(F.desc("score"), F.desc("wide"), "vec_id")
    top = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k + 1)
    own = F.min(F.when(F.col("own"), F.col("rank"))).over(Window.partitionBy("asker"))
    top = top.withColumn("mine", F.coalesce(own, F.lit(k + 2))).where(F.col("rank") != F.col("mine"))
    return top.withColumn("rank", F.col("rank") - (F.col("mine") < F.col("rank")).cast("int")).where(F.col("rank") <= k)


def top_k(vectors: DataFrame, k: int = 10, every: int = 100, scale: int = 1024) -> DataFrame:
    """vectors: vec_id long, embedding. Queries are the rows whose id is divisible by
    ``every``. query_id, rank, vec_id, score of each query's k best of all other rows.
    Null ids, null vectors and those with null or non-finite components take no part; of
    unequal lengths, the missing components count as zero. Other columns play no part."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")).where("vec_id is not null and embedding is not null")
    asked = rows.where(F.pmod("vec_id", F.lit(every)) == 0)
    size = asked.agg(F.sum(F.size("embedding") + 4)).first()[0] or 0
    rounds = max(1, -(-8 * size // ROUND_BYTES))
    spark, done = vectors.sparkSession, None
    for r in range(rounds):
        block = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(rounds)) == r).toArrow()
        ids = block.column("vec_id").to_pylist()
        queries = [(n, q, v) for n, (q, v) in enumerate(zip(ids, _whole(block.column("embedding").to_pylist(), scale), strict=True)) if v is not None]
        found = rows.mapInArrow(_accumulate(queries, k, scale), "asker long, vec_id long, score long, wide double, own boolean")
        names = spark.createDataFrame(pa.table({"asker": pa.array([n for n, *_ in queries], pa.int64()), "query_id": pa.array([q for _, q, _ in queries], pa.int64())}))
        best = _merged(found, k).join(F.broadcast(names), "asker")  # a row a query of the block
        part = best.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
        part = cut(part) if rounds > 1 else part
        done = part if done is None else done.unionByName(part)
    return done
