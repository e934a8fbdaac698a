"""Quality classifier: random Fourier features of document statistics, ridge regression by
partition-summed normal equations, isotonic calibration.

The features approximate a Gaussian kernel over standardised statistics of a text. Each
partition sums its outer products; the cells of those sums are added up by Spark, so what
reaches the driver has one number for each cell whatever the number of rows. Null and
empty texts have all-zero statistics and are scored as such.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, text_slices, texts_of

#: Tasks that a fit's rows are dealt to.
FIT_TASKS = 8

_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_STOP = np.zeros(256, bool)
_STOP[[33, 46, 63]] = True
_SYMBOL = ~(_LETTER | _DIGIT | _SPACE)
_CLASSES = np.stack([_LETTER, _UPPER, _DIGIT, _SPACE, _STOP, _SYMBOL & ~_STOP]).astype(np.float64)
STATISTICS = ("log_bytes", "letters", "upper", "digits", "blanks", "stops", "symbols", "byte_entropy", "log_words", "word_length", "distinct_words", "repeated_next", "log_lines", "distinct_lines", "line_words", "bare_marks", "marked_ends", "commonest_word", "long_words", "capitalised")


def statistics(text: str) -> list[float]:
    raw = text.encode("utf-8", "replace")
    n = len(raw)
    if not n:
        return [0.0] * len(STATISTICS)
    counts = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    shares = (_CLASSES @ counts) / n
    p = counts[counts > 0] / n
    words = text.split()
    w = max(1, len(words))
    tally: dict[str, int] = {}
    for x in words:
        tally[x] = tally.get(x, 0) + 1
    lines = text.split("\n")
    ends = [x[-1] for x in words]
    return [
        math.log1p(n), *shares.tolist(), float(-(p * np.log(p)).sum()), math.log1p(len(words)), sum(map(len, words)) / w, len(tally) / w,
        sum(map(str.__eq__, words, words[1:])) / w, math.log1p(len(lines)), len(set(lines)) / len(lines), math.log1p(len(words) / len(lines)),
        sum(not x[0].isalnum() and len(x) == 1 for x in words) / w, sum(not x.isalnum() and x not in ".,;:?" for x in ends) / w, max(tally.values(), default=0) / w,
        sum(c for x, c in tally.items() if len(x) > 18) / w, sum(x[0].isupper() for x in words) / w,
    ]


@dataclass
class QualityModel:
    mean: np.ndarray
    scale: np.ndarray
    directions: np.ndarray
    shifts: np.ndarray
    weights: np.ndarray
    steps: np.ndarray
    levels: np.ndarray

    def features(self, stats: np.ndarray) -> np.ndarray:
        z = np.clip((stats - self.mean) / self.scale, -8, 8)
        wave = np.cos(z @ self.directions + self.shifts) * math.sqrt(2 / self.shifts.size)
        return np.hstack([np.ones((len(z), 1)), wave])

    def margin(self, stats: np.ndarray) -> np.ndarray:
        return self.features(stats) @ self.weights

    def score(self, stats: np.ndarray) -> np.ndarray:
        if not self.steps.size:
            return np.full(len(stats), 0.5)
        return np.clip(np.interp(self.margin(stats), self.steps, self.levels), 0.0, 1.0)


def isotonic(x: np.ndarray, y: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators over points (x, mean y, n), x ascending: knots of a
    non-decreasing curve, drawn towards 1/2 by one row in a block."""
    blocks: list[list[float]] = []
    for xi, yi, ni in zip(x.tolist(), y.tolist(), n.tolist(), strict=True):
        blocks.append([xi, xi, yi * ni, ni])
        while len(blocks) > 1 and blocks[-2][2] * blocks[-1][3] >= blocks[-1][2] * blocks[-2][3]:
            _, hi, s, m = blocks.pop()
            blocks[-1] = [blocks[-1][0], hi, blocks[-1][2] + s, blocks[-1][3] + m]
    level = [(s + 0.5) / (m + 1) for _, _, s, m in blocks]
    level = np.maximum.accumulate(np.array(level))
    return np.array([v for b in blocks for v in b[:2]]), np.repeat(level, 2)


def fit_quality(labelled: DataFrame, width: int = 192, gamma: float = 0.02, ridge: float = 1.0, seed: int = 7, bins: int = 512) -> QualityModel:
    """labelled: doc_id, text, quality (0/1). The calibration curve is fitted on the half
    of the rows that the weights are not fitted on, then the weights on all."""
    dim = len(STATISTICS)

    def stats(batches):
        for b in text_slices(batches):
            x = np.array([statistics(t) for t in texts_of(b)], np.float64).reshape(-1, dim)
            yield pa.RecordBatch.from_arrays([pa.array(list(map(np.ndarray.tobytes, x)), pa.binary()), b.column("y"), b.column("half")], ["x", "y", "half"])

    rows = labelled.where("quality in (0, 1)").select("text", F.col("quality").cast("int").alias("y"), F.pmod(F.xxhash64("text"), F.lit(2)).cast("int").alias("half"))
    # the fit's rows are few, whatever number of partitions they come from: every partition sums all cells
    rows = cut(rows.mapInArrow(stats, "x binary, y int, half int").repartition(FIT_TASKS))

    def matrix(b):
        return np.frombuffer(b"".join(b.column("x").to_pylist()), np.float64).reshape(-1, dim)

    def moments(batches):
        total = np.zeros((2, dim))
        n = 0
        for b in batches:
            x = matrix(b)
            n += len(x)
            total += np.stack([x.sum(0), (x * x).sum(0)])
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(2 * dim + 1)), pa.array(np.r_[total.reshape(-1), n])], ["i", "v"])

    def summed(job, source):
        return {r["i"]: r["v"] for r in source.mapInArrow(job, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).collect()}

    got = summed(moments, rows)
    n = got.get(2 * dim, 0.0)
    if not n:
        return QualityModel(np.zeros(dim), np.ones(dim), np.zeros((dim, 1)), np.zeros(1), np.zeros(2), np.zeros(0), np.zeros(0))
    mean = np.array([got[i] for i in range(dim)]) / n
    var = np.array([got[dim + i] for i in range(dim)]) / n - mean**2
    rng = np.random.default_rng(seed)
    model = QualityModel(mean, np.sqrt(np.maximum(var, 0)) + 1e-6, rng.standard_normal((dim, width)) * math.sqrt(2 * gamma), rng.uniform(0, 2 * math.pi, width), np.zeros(width + 1), np.zeros(0), np.zeros(0))
    m = width + 1
    upper = np.triu_indices(m)

    def normal(batches):
        cells, right, n = np.zeros((2, m, m)), np.zeros((2, m)), 0
        for b in batches:
            n += b.num_rows
            z, y, half = model.features(matrix(b)), b.column("y").to_numpy(), b.column("half").to_numpy()
            for h in (0, 1):
                own = z[half == h]
                cells[h] += own.T @ own
                right[h] += own.T @ y[half == h]
        flat = np.concatenate([np.concatenate([cells[h][upper], right[h]]) for h in (0, 1)])
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(flat.size)), pa.array(flat)], ["i", "v"])

    cells = summed(normal, rows)
    size = upper[0].size + m
    both = np.array([cells[i] for i in range(2 * size)]).reshape(2, size)

    def solve(flat):
        a = np.zeros((m, m))
        a[upper] = flat[: upper[0].size]
        a = a + np.triu(a, 1).T
        penalty = np.full(m, ridge)
        penalty[0] = 1e-6
        return np.linalg.solve(a + np.diag(penalty), flat[upper[0].size :])

    halves = [solve(both[1]), solve(both[0])]

    def margins(batches):
        for b in batches:
            z, half = model.features(matrix(b)), b.column("half").to_numpy()
            out = np.where(half == 0, z @ halves[0], z @ halves[1])
            yield pa.RecordBatch.from_arrays([pa.array(np.clip(np.round(out * bins / 2), -bins, bins).astype(np.int64)), b.column("y")], ["i", "y"])

    tally = rows.mapInArrow(margins, "i long, y int").groupBy("i").agg(F.count(F.lit(1)).alias("n"), F.sum("y").alias("y")).orderBy("i").collect()
    count = np.array([r["n"] for r in tally], float)
    model.steps, model.levels = isotonic(np.array([r["i"] for r in tally]) * 2 / bins, np.array([r["y"] for r in tally]) / count, count)
    model.weights = solve(both.sum(0))
    return model


def score_quality(docs: DataFrame, model: QualityModel) -> DataFrame:
    """doc_id and score (0 to 1) of each row; other columns play no part."""

    def run(batches):
        for b in text_slices(batches):
            x = np.array([statistics(t) for t in texts_of(b)], np.float64).reshape(-1, len(STATISTICS))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.score(x), pa.float64())], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, score double")
