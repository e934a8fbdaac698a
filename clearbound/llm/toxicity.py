"""Toxicity by a weighted finite-state pattern grammar.

Five transducers read a clause in a cascade, each the output of the one before: insults,
threats, targets, negation and reported speech. The first two choose one head, an insult
or a threat; the third looks for whom it is aimed at, before it or after it; the fourth
and fifth weaken a head that is denied or that somebody is said to have said. A path is
accepted only if it has a head and its final states accept: a threat needs a target, an
insult without one is accepted at the weight of an implied target, which the labels
choose and which may be 0. Words on no accepted path count nothing. A clause weighs the
sum over its accepted paths of their arc weights; a logistic curve maps a document's summed
clause weights to a score. Null and empty texts have no clause: they get the curve's value
at zero.

Insult arcs are seed words, and words and prefixes learned from labels. Thresholds and the
curve come from the learning rows alone: each of FOLDS parts of them is scored by arcs that
the others taught, and the setting of least log loss wins.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, cut, fold, text_slices, texts_of

# Seed words of each class.
INSULTS = ("idiot", "moron", "stupid", "dumb", "scum", "trash", "garbage", "loser", "worthless", "pathetic", "disgusting", "clown", "vermin", "imbecile", "filth")
THREATS = ("kill", "hurt", "destroy", "beat", "burn", "shoot", "stab", "crush", "punch", "murder")
TARGETS = ("you", "your", "yours", "yourself", "u", "he", "she", "they", "him", "her", "them", "people", "everyone")
NEGATIONS = ("not", "no", "never", "isn", "aren", "wasn", "don", "doesn", "didn", "nobody", "none", "without", "hardly")
REPORTS = ("said", "says", "wrote", "claimed", "called", "calls", "according", "quoted", "reported", "alleged", "told")

WORD = re.compile(r"\w+")
CLAUSE = re.compile(r"[.!?;:\n\r\"()]+|,\s")
PREFIXES = (4, 5, 6, 7)
#: Parts of the learning rows that are scored in turn by what the others teach.
FOLDS = 8
#: Words whose weights a worker remembers at once.
MEMORY = 300_000


@dataclass(frozen=True, eq=False)
class Transducer:
    """arcs: (state, symbol) -> [(output, next state, weight)], several where the machine may
    choose; a symbol without an arc passes through and leaves the state, at weight 1.
    final: the states that accept, and their weights. Starts in state 0."""

    arcs: dict[tuple[int, str], list[tuple[str, int, float]]]
    final: dict[int, float]
    fades: dict[int, int] = field(default_factory=dict)

    def step(self, state: int, symbol: str) -> list[tuple[str, int, float]]:
        found = self.arcs.get((state, symbol))
        return found if found is not None else [(symbol, self.fades.get(state, state), 1.0)]


#: One insult becomes the head ("insulting"), or none and the head is a threat.
INSULT = Transducer({(0, "insult"): [("insulting", 1, 1.0), ("other", 0, 1.0)], (1, "insult"): [("other", 1, 1.0)]}, {0: 1.0, 1: 1.0})
#: One threat becomes the head where no insult is; without a head nothing is accepted.
THREAT = Transducer(
    {(0, "insulting"): [("insulting", 1, 1.0)], (0, "threat"): [("threatening", 1, 1.0), ("other", 0, 1.0)], (1, "threat"): [("other", 1, 1.0)], (1, "insulting"): []},
    {1: 1.0},
)


def target_machine(implied: float, aimed: float = 1.5, threatened: float = 2.0) -> Transducer:
    """States: 0 no target, 1 a target, 2 an insult that waits for one, 3 aimed, 4 a threat
    that waits for one, which is not accepted."""
    return Transducer(
        {
            (0, "target"): [("target", 1, 1.0)],
            (0, "insulting"): [("head", 2, 1.0)], (1, "insulting"): [("head", 3, aimed)], (2, "target"): [("target", 3, aimed)],
            (0, "threatening"): [("head", 4, 1.0)], (1, "threatening"): [("head", 3, threatened)], (4, "target"): [("target", 3, threatened)],
        },
        {2: implied, 3: 1.0},
    )


#: A negation reaches over three words, and another one within them takes it back.
NEGATION = Transducer(
    {(0, "negation"): [("other", 3, 1.0)], **{(s, "negation"): [("other", 0, 1.0)] for s in (1, 2, 3)}, **{(s, "head"): [("head", s - 1, 0.3)] for s in (1, 2, 3)}},
    dict.fromkeys(range(4), 1.0),
    {3: 2, 2: 1, 1: 0},
)
#: Reported speech before the head or after it; states: 0 none, 1 a report, 2 a head, 3 done.
REPORTED = Transducer(
    {(0, "report"): [("other", 1, 1.0)], (1, "head"): [("head", 3, 0.5)], (0, "head"): [("head", 2, 1.0)], (2, "report"): [("other", 3, 0.5)]},
    dict.fromkeys(range(4), 1.0),
)


@lru_cache(maxsize=16)
def grammar(implied: float = 0.5) -> tuple[Transducer, ...]:
    return (INSULT, THREAT, target_machine(implied), NEGATION, REPORTED)


def _through(machines: tuple[Transducer, ...], states: tuple[int, ...], symbol: str) -> list[tuple[tuple[int, ...], str, float]]:
    """Every way of the cascade over one symbol: (next states, what the last machine puts out, weight)."""
    ways = [((), symbol, 1.0)]
    for machine, state in zip(machines, states, strict=True):
        ways = [((*done, after), out, w * k) for done, read, w in ways for out, after, k in machine.step(state, read)]
    return ways


@lru_cache(maxsize=1 << 16)
def _moves(machines: tuple[Transducer, ...], states: tuple[int, ...], symbol: str) -> tuple[tuple[tuple[int, ...], bool, float], ...]:
    """The steps of the composed machine, which is built as far as texts lead into it:
    (next states, whether the word comes out as the head, weight). Ways that end in no
    accepting path, because a machine's state leaves none, are kept out by the finals."""
    return tuple((to, out == "head", k) for to, out, k in _through(machines, states, symbol))


def clause_weight(symbols: list[str], weights: list[float], machines: tuple[Transducer, ...]) -> float:
    """Sum over the accepted paths of a clause. ``weights``: the arc weight of each word,
    which counts where the word comes out of the cascade as the head."""
    front: dict[tuple[int, ...], float] = {(0,) * len(machines): 1.0}
    for symbol, weight in zip(symbols, weights, strict=True):
        after: dict[tuple[int, ...], float] = {}
        for states, so_far in front.items():
            for to, head, k in _moves(machines, states, symbol):
                after[to] = after.get(to, 0.0) + so_far * (k * weight if head else k)
        front = after
    total = 0.0
    for states, w in front.items():
        for machine, state in zip(machines, states, strict=True):
            w *= machine.final.get(state, 0.0)
        total += w
    return total


_KINDS = {w: k for k, ws in (("threat", THREATS), ("target", TARGETS), ("negation", NEGATIONS), ("report", REPORTS)) for w in ws}


def text_weight(low: str, heads: dict[str, tuple[str, float]], machines: tuple[Transducer, ...]) -> float:
    """Summed clause weights of a lower-cased text. heads: symbol and arc weight of the words
    that can be a head."""
    if not heads:
        return 0.0
    total = 0.0
    for clause in CLAUSE.split(low):
        words = WORD.findall(clause)
        if not heads.keys().isdisjoint(words):
            total += clause_weight([heads[w][0] if w in heads else _KINDS.get(w, "other") for w in words], [heads[w][1] if w in heads else 1.0 for w in words], machines)
    return total


def _head(w: str, weight: float) -> tuple[str, float] | None:
    """Symbol and arc weight of a word whose insult arc weighs this much (0: it has none)."""
    return ("insult", weight) if weight > 0 else ("threat", 1.0) if _KINDS.get(w) == "threat" else None


def _longest(w: str, prefixes: dict[str, float], lengths: list[int]) -> float:
    """The largest weight of the prefixes of a word."""
    return max((prefixes.get(w[:n], 0.0) for n in lengths if len(w) > n), default=0.0)


@dataclass
class ToxicityModel:
    words: dict[str, float]
    prefixes: dict[str, float]
    bias: float
    slope: float
    implied: float = 0.5

    def __post_init__(self):
        self.lengths = sorted({len(p) for p in self.prefixes})
        self.known: dict[str, tuple[str, float] | None] = {}

    def __getstate__(self):
        return {**self.__dict__, "known": {}}

    def raw(self, text: str) -> float:
        low, known = text.lower(), self.known
        words = set(WORD.findall(low))
        if len(known) > MEMORY:
            known.clear()
        for w in words.difference(known):
            known[w] = _head(w, max(self.words.get(w, 0.0), _longest(w, self.prefixes, self.lengths)))
        return text_weight(low, {w: h for w in words if (h := known[w])}, grammar(self.implied))

    def score(self, text: str) -> float:
        return logistic(self.bias + self.slope * math.log1p(self.raw(text)))


def logistic(z: float) -> float:
    return 1.0 / (1.0 + math.exp(-max(-40.0, min(40.0, z))))


def _terms(text: str) -> set[str]:
    words = set(WORD.findall(text.lower()))
    return words | {w[:n] + "*" for w in words for n in PREFIXES if len(w) > n}


_COUNTS = [f"{side}{k}" for side in "ab" for k in range(FOLDS)]


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts that hold a term, by fold: toxic ones (a0, a1, ...) and others (b0, b1, ...)."""
    for b in text_slices(batches):
        found: dict[str, list[int]] = {}
        for text, toxic, part in zip(texts_of(b), b.column("toxic").to_pylist(), b.column("fold").to_pylist(), strict=True):
            at = part if toxic else FOLDS + part
            for t in _terms(text):
                if t not in found:
                    found[t] = [0] * len(_COUNTS)
                found[t][at] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.string()), *(pa.array(c, pa.int64()) for c in np.array(list(found.values()), np.int64).reshape(-1, len(_COUNTS)).T)], ["term", *_COUNTS])


def certain_lift(a: float, b: float, pos: float, neg: float) -> float:
    """Log ratio of a term's share of toxic texts (a of pos) to that of the others (b of neg),
    less two standard errors: rare terms are believed less, at any number of rows."""
    return math.log((a + 0.25) / (pos + 0.5) * (neg + 0.5) / (b + 0.25)) - 2 * math.sqrt(1 / (a + 0.5) + 1 / (b + 0.5))


def _weight(lift: float) -> float:
    """Arc weight of a lift: its cube, so that one sure word outweighs several doubtful ones (of
    powers from 1 to 6 the one of least log loss across folds of the learning rows)."""
    return lift**3


#: Lift that a seed word is taken to have.
SEED = 3.0


def _arcs(lifts: dict[str, float], word: float, prefix: float) -> tuple[dict[str, float], dict[str, float]]:
    words, prefixes = dict.fromkeys(INSULTS, _weight(SEED)), {}
    for term, lift in lifts.items():
        if term.endswith("*"):
            if lift >= prefix:
                prefixes[term[:-1]] = _weight(lift)
        elif lift >= word and term not in _KINDS:
            words[term] = _weight(lift)
    return words, prefixes


#: Settings that the learning rows choose among: least lift of a word, of a prefix, weight of an implied target.
SETTINGS = [(word, prefix, implied) for implied in (0.0, 0.5) for word in (3.0, 2.0, 1.0, 0.5) for prefix in (4.0, 3.0, 2.0, 1.0)]


def _curve(points: list[tuple[float, int, int]]) -> tuple[float, float, float]:
    """Logistic curve of x by Newton steps with a small ridge, and its log loss; points: (x, label, rows)."""
    bias, slope = -2.0, 1.0
    for _ in range(60):
        g0, g1, h00, h01, h11 = 0.01 * (bias + 2), 0.01 * (slope - 1), 0.01, 0.0, 0.01
        for x, label, n in points:
            p = logistic(bias + slope * x)
            g0, g1 = g0 + n * (p - label), g1 + n * (p - label) * x
            v = n * p * (1 - p)
            h00, h01, h11 = h00 + v, h01 + v * x, h11 + v * x * x
        det = h00 * h11 - h01 * h01
        d0, d1 = (h11 * g0 - h01 * g1) / det, (h00 * g1 - h01 * g0) / det
        most = max(abs(d0), abs(d1), 1.0)
        bias, slope = bias - d0 / most, slope - d1 / most
        if max(abs(d0), abs(d1)) < 1e-6:
            break
    slope = max(slope, 0.0)
    loss = -sum(n * math.log(max(1e-12, p if label else 1 - p)) for x, label, n in points for p in [logistic(bias + slope * x)])
    return bias, slope, loss


def fit_toxicity(labelled: DataFrame) -> ToxicityModel:
    """labelled: text, toxic (0/1); rows of one text count once, as toxic if any is. What
    comes to the driver is the terms of the given rows that some setting takes, and tables
    of rounded weights; the rows are to be a bounded sample. The same rows give the same
    model however they are partitioned. Null texts and other labels are left out; without
    rows of both labels the seeds alone make the arcs."""
    rows = labelled.where("toxic in (0, 1) and text is not null").groupBy("text").agg(F.max("toxic").cast("int").alias("toxic"))
    # copies of a text mostly have one least word hash, so they fall in one fold and confirm nothing
    least_word = F.array_min(F.transform(F.split(F.lower("text"), r"\s+"), lambda w: F.xxhash64(w)))
    rows = cut(rows.withColumn("fold", F.pmod(least_word, F.lit(FOLDS)).cast("int")))
    sizes = {(r["toxic"], r["fold"]): r["count"] for r in rows.groupBy("toxic", "fold").count().collect()}
    pos, neg = ([sizes.get((toxic, k), 0) for k in range(FOLDS)] for toxic in (1, 0))
    if not sum(pos) or not sum(neg):
        return ToxicityModel(*_arcs({}, 0.0, 0.0), -2.0, 2.0)
    counted = rows.mapInArrow(_count, ", ".join(["term string", *(f"{c} long" for c in _COUNTS)])).groupBy("term").agg(*(F.sum(c).alias(c) for c in _COUNTS))
    # in toxic texts of two folds, and twice as common there: any setting asks for more
    of = lambda side: sum((F.col(f"{side}{k}") for k in range(FOLDS)), F.lit(0))
    spread = sum(((F.col(f"a{k}") > 0).cast("int") for k in range(FOLDS)), F.lit(0))
    counted = counted.where((spread > 1) & (of("a") * sum(neg) > 2 * of("b") * sum(pos)))
    counts = {r["term"]: ([r[c] for c in _COUNTS[:FOLDS]], [r[c] for c in _COUNTS[FOLDS:]]) for r in counted.collect()}
    least = min(min(word, prefix) for word, prefix, _ in SETTINGS)

    def lifts(without: int | None) -> dict[str, float]:
        rest = [k for k in range(FOLDS) if k != without]
        total = lambda x: sum(x[k] for k in rest)
        taken = {t: certain_lift(total(a), total(b), total(pos), total(neg)) for t, (a, b) in counts.items()}
        return {t: v for t, v in sorted(taken.items()) if v >= least}

    taught = [lifts(k) for k in range(FOLDS)]  # the arcs that score each fold are the others'

    lengths = list(PREFIXES)

    def crossed(batches):
        arcs = [_arcs(t, least, least) for t in taught]  # the loosest setting's
        known: list[dict[str, tuple[float, float]]] = [{} for _ in arcs]
        for b in text_slices(batches):
            tally: Counter = Counter()
            for text, toxic, part in zip(texts_of(b), b.column("toxic").to_pylist(), b.column("fold").to_pylist(), strict=True):
                low, own, (words, prefixes) = text.lower(), known[part], arcs[part]
                found = set(WORD.findall(low))
                for w in found.difference(own):
                    own[w] = words.get(w, 0.0), _longest(w, prefixes, lengths)
                some = [w for w in found if any(own[w]) or _KINDS.get(w) == "threat"]
                done: dict = {}
                for k, (word, prefix, implied) in enumerate(SETTINGS):
                    heads = {w: h for w in some for x, y in [own[w]] if (h := _head(w, max(x if x >= _weight(word) else 0.0, y if y >= _weight(prefix) else 0.0)))}
                    key = (implied, tuple(sorted(heads.items()))) if heads else ()
                    if key not in done:
                        done[key] = round(math.log1p(text_weight(low, heads, grammar(implied))), 1)
                    tally[k, done[key], toxic] += 1
            keys = list(tally)
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys], pa.float64()), pa.array([k[2] for k in keys], pa.int32()), pa.array([tally[k] for k in keys], pa.int64())], ["setting", "x", "toxic", "n"])

    points: dict[int, list] = {k: [] for k in range(len(SETTINGS))}
    for r in rows.mapInArrow(crossed, "setting int, x double, toxic int, n long").groupBy("setting", "x", "toxic").agg(F.sum("n").alias("n")).orderBy("setting", "x", "toxic").collect():
        points[r["setting"]].append((r["x"], r["toxic"], r["n"]))
    curves = {k: _curve(p) for k, p in points.items()}
    best = min(curves, key=lambda k: (round(curves[k][2], 6), k))
    word, prefix, implied = SETTINGS[best]
    return ToxicityModel(*_arcs(lifts(None), word, prefix), curves[best][0], curves[best][1], implied)


def score_toxicity(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, raw clause weight and score of each row, null ids and repeated ids included; other
    columns play no part."""

    def run(batches):
        for b in text_slices(batches):
            raw = [model.raw(t) for t in texts_of(b)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(raw, pa.float64()), pa.array([logistic(model.bias + model.slope * math.log1p(r)) for r in raw], pa.float64())], [id_col, "raw", "score"])

    picked = docs.select(F.col(id_col), F.col(text_col).alias("text"))
    return picked.mapInArrow(run, f"`{id_col}` {dict(docs.dtypes)[id_col]}, raw double, score double")


def training_rows(docs: DataFrame, labels: DataFrame, label: str, held: tuple[int, int], rows: int) -> DataFrame:
    """Labelled rows outside the held-out fold: (modulus, remainder) of ``held``. At most
    about ``rows`` of them, so the label side of the join is bounded and is broadcast. An id
    that is labelled twice has the larger label; null ids and labels are left out."""
    own = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & (fold("doc_id", held[0]) != held[1]))
    own = own.groupBy("doc_id").agg(F.max(label).cast("int").alias(label))
    return docs.select("doc_id", "text").join(F.broadcast(bounded_sample(own, "doc_id", rows)), "doc_id")
