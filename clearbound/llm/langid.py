"""Language identification by interpolated Kneser-Ney character models.

Each language has a model of the characters of words (lower-cased runs of letters with
marks before and after). Grams of every order are 64-bit hashes of their characters, kept
in sorted arrays that all languages share, with a column of log probabilities for each. A
text gets the language of the lowest cross-entropy a character. Part of the training texts
is kept from the counts to calibrate with: the score is a softmax of the entropies whose
temperature makes it honest on them, and a text is rejected beyond a limit of its language
that is set between those texts and the same texts with their letters shuffled. Words are
scored once and remembered, so a text costs a look-up and a row sum a word.

Null texts, empty ones and those without a letter get 'und', score 0 and are not accepted;
so does every text where no language was learned. Rows that repeat an id are rows of their
own; other columns play no part.
"""

from __future__ import annotations

import random
import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, cut, text_slices, texts_of

WORD = re.compile(r"[^\W\d_]+")
ORDER = 4
UNDETERMINED = "und"
#: Words, and characters of words, whose scores a worker remembers at once.
MEMORY, MEMORY_CHARS = 250_000, 2_000_000
#: Training texts a language, and the share of them that calibrates.
SAMPLE, CALIBRATING = 3_000, 10
_START, _END = 2, 1


def _windows(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """ORDER-grams of the words as rows of characters and the word of each: one for each
    character and one for the mark at the end. A word stands behind ORDER - 1 marks."""
    chars = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4")
    n = np.fromiter(map(len, words), np.int64, len(words))
    size = n + ORDER
    first = np.cumsum(size) - size
    line = np.full(int(size.sum()), _START, np.uint32)
    line[first + size - 1] = _END
    line[np.arange(chars.size) + np.repeat(first - (np.cumsum(n) - n), n) + ORDER - 1] = chars
    row = np.repeat(np.arange(len(words)), n + 1)
    at = np.arange(row.size) + np.repeat(first - (np.cumsum(n + 1) - (n + 1)), n + 1)
    return line[at[:, None] + np.arange(ORDER)], row


def _hash(grams: np.ndarray) -> np.ndarray:
    """64-bit hashes of rows of characters."""
    h = np.full(len(grams), grams.shape[1], np.uint64)
    for k in range(grams.shape[1]):
        h = (h ^ grams[:, k]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


@dataclass
class Table:
    """Sorted hashes with a row of values each."""

    keys: np.ndarray
    values: np.ndarray

    def find(self, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not self.keys.size:
            return np.zeros(wanted.size, np.int64), np.zeros(wanted.size, bool)
        at = np.minimum(np.searchsorted(self.keys, wanted), self.keys.size - 1)
        return at, self.keys[at] == wanted


@dataclass
class LanguageModel:
    """grams[n - 1]: log probability of each n-gram's last character by language; rest[n - 1]:
    log of what the context of n - 1 characters leaves to lower orders (0: unseen context);
    unseen: log probability of a character that a language never saw."""

    langs: list[str]
    grams: list[Table]
    rest: list[Table]
    unseen: np.ndarray
    temperature: float = 1.0
    usual: np.ndarray = field(default_factory=lambda: np.zeros(0))
    spread: np.ndarray = field(default_factory=lambda: np.zeros(0))
    limit: np.ndarray = field(default_factory=lambda: np.zeros(0))
    memory: dict = field(default_factory=dict, repr=False)

    def __getstate__(self):
        return {**self.__dict__, "memory": {}}

    def gram_scores(self, grams: np.ndarray) -> np.ndarray:
        """Log probability of each gram's last character after the others, by language."""
        out = np.zeros((len(grams), len(self.langs)))
        left = np.arange(len(grams))
        for n in range(min(ORDER, grams.shape[1]), 0, -1):
            own = grams[left, grams.shape[1] - n :]
            at, hit = self.grams[n - 1].find(_hash(own))
            out[left[hit]] += self.grams[n - 1].values[at[hit]]
            left, own = left[~hit], own[~hit]
            at, seen = self.rest[n - 1].find(_hash(own[:, :-1]))
            out[left[seen]] += self.rest[n - 1].values[at[seen]]
            if not left.size:
                break
        out[left] += self.unseen
        return out

    def word_scores(self, words: list[str]) -> np.ndarray:
        grams, row = _windows(words)
        _, first, back = np.unique(_hash(grams), return_index=True, return_inverse=True)
        s = self.gram_scores(grams[first])[back]
        return np.stack([np.bincount(row, s[:, k], len(words)) for k in range(len(self.langs))], axis=1)

    def entropies(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Nats a character by language (lower is likelier), and the characters scored."""
        found = [WORD.findall(t.lower()) for t in texts]
        found = [w if any(c.isalpha() for x in w for c in x) else [] for w in found]
        known = self.memory
        if len(known.get("at", ())) > MEMORY or known.get("chars", 0) > MEMORY_CHARS:
            known.clear()
        at = known.setdefault("at", {})
        new = list(set().union(*found).difference(at))
        if new or "rows" not in known:
            rows, old, n = self.word_scores(new), known.get("rows"), len(at)
            if old is None or n + len(new) > len(old):
                grown = np.zeros((max(2 * (n + len(new)), 1024), len(self.langs)))
                if old is not None:
                    grown[:n] = old[:n]
                known["rows"] = grown
            known["rows"][n : n + len(new)] = rows
            at.update(zip(new, range(n, n + len(new)), strict=True))
            known["chars"] = known.get("chars", 0) + sum(map(len, new))
        sizes = np.fromiter(map(len, found), np.int64, len(found))
        index = np.fromiter((at[w] for ws in found for w in ws), np.int64, int(sizes.sum()))
        total = np.zeros((len(texts), len(self.langs)))
        chars = np.fromiter((sum(map(len, w)) + len(w) for w in found), np.int64, len(found))
        some = np.flatnonzero(sizes)
        if some.size:
            total[some] = np.add.reduceat(known["rows"][index], (np.cumsum(sizes) - sizes)[some], axis=0)
        return -total / np.maximum(chars, 1)[:, None], chars

    def excess(self, h: np.ndarray, chars: np.ndarray, k: np.ndarray) -> np.ndarray:
        """Nats a character over what language k has, less what texts so short vary by."""
        return h - self.usual[k] - 3 * self.spread[k] / np.sqrt(chars)

    def classify(self, texts: list[str]) -> list[tuple[str, float, float | None, bool]]:
        """(language, score, nats a character, accepted) of each text."""
        if not self.langs:
            return [(UNDETERMINED, 0.0, None, False)] * len(texts)
        h, chars = self.entropies(texts)
        n = np.maximum(chars, 1)
        k = np.argmin(h, axis=1)
        least = h[np.arange(len(h)), k]
        score = 1 / np.exp(-(h - least[:, None]) * n[:, None] * self.temperature).sum(1)
        ok = self.excess(least, n, k) <= self.limit[k]
        rows = zip(k.tolist(), score.tolist(), least.tolist(), ok.tolist(), chars.tolist(), strict=True)
        return [(self.langs[i], s, e, good) if some else (UNDETERMINED, 0.0, None, False) for i, s, e, good, some in rows]


def build_model(counts: dict[str, tuple[np.ndarray, np.ndarray]]) -> LanguageModel:
    """counts: for each language its ORDER-grams (rows of characters) and how often each
    occurs. The highest order uses these counts, a lower one the number of different
    characters before a gram, and every order is discounted by its own share of grams seen
    once against twice. The lowest is mixed with an equal share for each character of the
    alphabet of all languages and for one that none has, so each order sums to one."""
    langs = sorted(counts)
    levels: list[list[tuple[np.ndarray, np.ndarray]]] = []
    for lang in langs:
        g, c = counts[lang]
        own = [(g, c.astype(float))]
        for n in range(ORDER - 1, 0, -1):
            tails = own[0][0][:, 1:]
            _, first, back = np.unique(_hash(tails), return_index=True, return_inverse=True)
            own.insert(0, (tails[first], np.bincount(back).astype(float)))
        levels.append(own)
    alphabet = len({int(c) for own in levels for c in own[0][0][:, 0]}) + 1
    model = LanguageModel(langs, [], [], np.zeros(len(langs)))
    for n in range(1, ORDER + 1):
        every, first = np.unique(np.concatenate([_hash(own[n - 1][0]) for own in levels]), return_index=True) if langs else (np.zeros(0, np.uint64), np.zeros(0, int))
        grams = np.concatenate([own[n - 1][0] for own in levels])[first] if langs else np.zeros((0, n), np.uint32)
        contexts = np.unique(_hash(grams[:, :-1]))
        values, rest = np.zeros((every.size, len(langs))), np.zeros((contexts.size, len(langs)))
        lower = np.full((every.size, len(langs)), -np.log(alphabet)) if n == 1 else model.gram_scores(grams[:, 1:])
        of = np.searchsorted(contexts, _hash(grams[:, :-1]))
        for k, own in enumerate(levels):
            g, c = own[n - 1]
            once, twice = (c == 1).sum(), (c == 2).sum()
            d = once / (once + 2 * twice) if once and twice else 0.5
            at, context = np.searchsorted(every, _hash(g)), np.searchsorted(contexts, _hash(g[:, :-1]))
            total = np.bincount(context, c, contexts.size)
            left = np.where(total > 0, d * np.bincount(context, minlength=contexts.size) / np.maximum(total, 1), 1.0)
            seen = np.zeros(every.size)
            seen[at] = (c - d) / total[context]
            values[:, k] = np.log(seen + left[of] * np.exp(lower[:, k]))
            rest[:, k] = np.log(left)
        model.grams.append(Table(every, values))
        model.rest.append(Table(contexts, rest))
        if n == 1 and langs:
            model.unseen = np.full(len(langs), -np.log(alphabet))
    return model


def _count(batches):
    for b in text_slices(batches):
        by: dict[str, Counter] = {}
        for lang, t in zip(b.column("lang").to_pylist(), texts_of(b), strict=True):
            by.setdefault(lang, Counter()).update(WORD.findall(t.lower()))
        for lang, tally in by.items():
            if not tally:
                continue
            grams, row = _windows(list(tally))
            _, first, back = np.unique(_hash(grams), return_index=True, return_inverse=True)
            n = np.bincount(back, np.fromiter(tally.values(), np.float64, len(tally))[row])
            yield pa.RecordBatch.from_arrays([pa.array([lang] * first.size), pa.array([g.tobytes() for g in np.ascontiguousarray(grams[first])], pa.binary()), pa.array(n.astype(np.int64))], ["lang", "gram", "n"])


def _shuffled(text: str) -> str:
    """The text with its letters in another order, the same for the same text."""
    letters = [c for c in text if c.isalpha()]
    random.Random(len(letters)).shuffle(letters)
    rest = iter(letters)
    return "".join(next(rest) if c.isalpha() else c for c in text)


def calibrate(model: LanguageModel, right: np.ndarray, h: np.ndarray, chars: np.ndarray, noise: np.ndarray, noise_chars: np.ndarray) -> None:
    """Sets the temperature, and for each language what its texts usually have and the limit
    beyond which a text is rejected. right: the language of each calibrating text; h, noise:
    entropies of the texts and of the same with their letters shuffled."""
    rows = np.arange(len(h))
    gaps = (h - h.min(1, keepdims=True)) * chars[:, None]

    def loss(t: float) -> float:
        z = -t * gaps
        return float((np.log(np.exp(z).sum(1)) - z[rows, right]).sum())

    model.temperature = min((2.0**-k for k in range(13)), key=loss) if len(h) else 1.0
    every, nearest, like = len(model.langs), np.argmin(h, axis=1), np.argmin(noise, axis=1)
    model.usual, model.spread, model.limit = np.zeros(every), np.zeros(every), np.full(every, np.inf)
    for k in range(every):
        own = nearest == k  # texts that get the language, as those to be rejected do
        if not own.any():
            continue
        model.usual[k] = np.average(h[own, k], weights=chars[own])
        model.spread[k] = np.sqrt(np.mean((h[own, k] - model.usual[k]) ** 2 * chars[own]))
        there = model.excess(h[own, k], chars[own], np.full(own.sum(), k))
        not_there = model.excess(noise[like == k, k], noise_chars[like == k], np.full((like == k).sum(), k))
        most = float(there.max())
        beyond = not_there[not_there > most]
        # the middle of the gap; without shuffled texts beyond it, as far again as the texts spread
        model.limit[k] = (most + float(np.quantile(beyond, 0.05))) / 2 if beyond.size else most + max(0.5, most - float(there.min()))


def fit_langid(rows: DataFrame, sample: int = SAMPLE) -> LanguageModel:
    """rows: doc_id, text, lang. Fitted on about ``sample`` rows of each language, of which one
    in CALIBRATING calibrates; their grams and the entropies of the calibrating rows are
    what comes to the driver. Rows without lang or text teach nothing."""
    own = rows.where("lang is not null and text is not null").select("doc_id", "text", "lang")
    own = cut(bounded_sample(own, "doc_id", sample, "lang").withColumn("apart", F.pmod(F.xxhash64("text"), F.lit(CALIBRATING)) == 0))
    few = [r["lang"] for r in own.groupBy("lang").agg(F.count_if(~F.col("apart")).alias("n")).where("n = 0").collect()]
    teaching = own.where(~F.col("apart") | F.col("lang").isin(few)) if few else own.where(~F.col("apart"))
    tallied = teaching.select("text", "lang").mapInArrow(_count, "lang string, gram binary, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).toArrow()
    langs, grams, n = tallied.column("lang").to_numpy(), tallied.column("gram").to_pylist(), tallied.column("n").to_numpy()
    counts = {}
    for lang in sorted(set(langs)):
        at = np.flatnonzero(langs == lang)
        at = at[np.argsort([grams[i] for i in at])]  # one order, whatever the partitions
        counts[lang] = (np.frombuffer(b"".join(grams[i] for i in at), "<u4").reshape(-1, ORDER), n[at])
    model = build_model(counts)
    if not model.langs:
        return model

    def entropy(batches):
        for b in text_slices(batches):
            texts = texts_of(b)
            (h, chars), (noise, noise_chars) = model.entropies(texts), model.entropies([_shuffled(t) for t in texts])
            keep = np.flatnonzero((chars > 0) & (noise_chars > 0))
            lists = [pa.array(x[keep].tolist(), pa.list_(pa.float64())) for x in (h, noise)]
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(keep)), *lists, pa.array(chars[keep]), pa.array(noise_chars[keep])], ["lang", "h", "noise", "n", "m"])

    held = own.where("apart").select("lang", "text").mapInArrow(entropy, "lang string, h array<double>, noise array<double>, n long, m long").toArrow().to_pydict()
    known = {lang: k for k, lang in enumerate(model.langs)}
    keep = [i for i, lang in enumerate(held["lang"]) if lang in known]
    at = lambda c, kind=float: np.array([held[c][i] for i in keep], kind)
    shape = (len(keep), len(model.langs))
    calibrate(model, np.array([known[held["lang"][i]] for i in keep], int), at("h").reshape(shape), at("n"), at("noise").reshape(shape), at("m"))
    return model


def predict_language(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score, nats_per_char and accepted of each row."""

    def run(batches):
        for b in text_slices(batches):
            langs, scores, nats, ok = zip(*model.classify(texts_of(b)), strict=True)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(nats, pa.float64()), pa.array(ok, pa.bool_())], ["doc_id", "lang_pred", "score", "nats_per_char", "accepted"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, lang_pred string, score double, nats_per_char double, accepted boolean")
