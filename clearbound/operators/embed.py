"""Embedders behind one interface: text -> unit vector. They stand in for neural models:
E1 hashed character 4-grams, E2 hashed words with inverse document frequency, E3 a column
of given vectors. They see shared wording only, no meaning, and no other language."""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as X
from ..sources.tables import spread

WIDTH = 1024
IDF_WIDTH = 1 << 18
_COMMAND = re.compile(r"\\[a-z]+")


def normalize_text(x: str) -> str:
    """By whole-string replacements, which took a tenth of the time of three expressions."""
    x = x.lower()
    if "\\" in x:
        x = _COMMAND.sub(" ", x)
    for c in "$(){}[],\t\n\r\f":
        if c in x:
            x = x.replace(c, " ")
    while "  " in x:
        x = x.replace("  ", " ")
    return x.strip(" ")


def feature_hash(term: str) -> tuple[int, int]:
    """(hash, sign) of a term: hash is the first eight hex digits of its md5, sign the ninth's parity."""
    d = hashlib.md5(term.encode()).hexdigest()
    return int(d[:8], 16), 1 - 2 * (int(d[8], 16) & 1)


@dataclass(frozen=True)
class CharGrams:
    """E1: 1 + log(tf) of character k-grams of the normalised text."""

    k: int = 4
    name: str = "E1"

    def terms(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """Different terms, and for each (text, term) that occurs its text, term and count."""
        clean = [normalize_text(x or "") for x in texts]
        chars = np.frombuffer("".join(clean).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
        n = np.fromiter(map(len, clean), np.int64, len(clean))
        row = np.repeat(np.arange(len(clean)), n)
        m = max(0, chars.size - self.k + 1)
        # four characters of 21 bits do not fit: numbers of characters do
        alphabet, code = np.unique(chars, return_inverse=True)
        key = np.zeros(m, np.uint64)
        for i in range(self.k):
            key = key * np.uint64(alphabet.size) + code[i : i + m].astype(np.uint64)
        own = row[:m] == row[self.k - 1 :] if m else np.zeros(0, bool)
        each, term = np.unique(key[own], return_inverse=True)
        pair, count = np.unique(row[:m][own] * max(1, each.size) + term, return_counts=True)
        letters = [chr(int(c)) for c in alphabet]
        words = []
        for v in each.tolist():
            w = []
            for _ in range(self.k):
                v, c = divmod(v, alphabet.size)
                w.append(letters[c])
            words.append("".join(reversed(w)))
        return words, pair // max(1, each.size), pair % max(1, each.size), count

    def encode(self, texts: list[str], memory: dict | None = None, clean: list[str] | None = None) -> np.ndarray:
        """Unit vectors of texts, of a bounded number at a time. ``memory`` keeps term hashes;
        ``clean``: the normalised texts, where the caller has them."""
        memory = {} if memory is None else memory
        if type(self) is CharGrams and self.k == 4:
            return self._encode_fours(texts, memory, clean)
        out = np.zeros((len(texts), WIDTH))
        words, row, term, count = self.terms(texts)
        if words:
            if len(memory) > 500_000:
                memory.clear()
            for w in words:
                if w not in memory:
                    h, sign = feature_hash(w)
                    memory[w] = (h % WIDTH, sign, h % IDF_WIDTH)
            slot, sign, idf = (np.array(c) for c in zip(*map(memory.__getitem__, words), strict=True))
            weight = sign * self.scale(idf)
            np.add.at(out, (row, slot[term]), weight[term] * (1 + np.log(count)))
        norm = np.sqrt((out * out).sum(1, keepdims=True))
        return np.divide(out, norm, out=out, where=norm > 0)

    def _encode_fours(self, texts: list[str], memory: dict, clean: list[str] | None = None) -> np.ndarray:
        """As ``encode``: four characters of 16 bits are one number, and hashes of numbers seen
        before are looked up. A text with other characters goes by ``terms``."""
        keys, counts, rows = [], [], []
        out = np.zeros((len(texts), WIDTH))
        other = memory.setdefault("other", {})
        clean = [normalize_text(x or "") for x in texts] if clean is None else clean
        for i, x in enumerate(texts):
            c = np.frombuffer(clean[i].encode("utf-32-le", "surrogatepass"), "<u4")
            if c.size < 4:
                continue
            if c.max() >= 0xD800:
                out[i] = CharGrams4(k=4).encode([x], other)[0]
                continue
            c = c.astype(np.uint64)
            key, n = np.unique(c[:-3] << np.uint64(48) | c[1:-2] << np.uint64(32) | c[2:-1] << np.uint64(16) | c[3:], return_counts=True)
            keys.append(key)
            counts.append(n)
            rows.append(np.full(key.size, i * WIDTH))
        if not keys:
            return out
        key = np.concatenate(keys)
        known, slot, sign = memory.get("fours", (np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0)))
        if known.size > 1_000_000:
            known, slot, sign = known[:0], slot[:0], sign[:0]
        at = np.searchsorted(known, key)
        new = np.unique(key[known[np.minimum(at, known.size - 1)] != key]) if known.size else np.unique(key)
        if new.size:
            shifts = (np.uint64(48), np.uint64(32), np.uint64(16), np.uint64(0))
            letters = "".join(map(chr, np.stack([new >> s & np.uint64(0xFFFF) for s in shifts], axis=1).reshape(-1).tolist()))
            found = [feature_hash(letters[k : k + 4]) for k in range(0, len(letters), 4)]
            known = np.r_[known, new]
            order = np.argsort(known, kind="stable")
            known = known[order]
            slot = np.r_[slot, np.array([h % WIDTH for h, _ in found], np.int64)][order]
            sign = np.r_[sign, np.array([float(s) for _, s in found])][order]
            at = np.searchsorted(known, key)
        memory["fours"] = known, slot, sign
        weight = sign[at] * (1 + np.log(np.concatenate(counts)))
        out += np.bincount(np.concatenate(rows) + slot[at], weight, out.size).reshape(out.shape)
        whole = np.unique(np.concatenate(rows) // WIDTH)
        norm = np.sqrt((out[whole] ** 2).sum(1, keepdims=True))
        out[whole] = np.divide(out[whole], norm, out=np.zeros((whole.size, WIDTH)), where=norm > 0)
        return out

    def scale(self, slots: np.ndarray) -> np.ndarray:
        return np.ones(slots.size)


class CharGrams4(CharGrams):
    """E1 by terms, for characters of any size."""


@dataclass(frozen=True)
class WordTfIdf(CharGrams):
    """E2: 1 + log(tf) of words times log((1 + N) / (1 + df)) + 1; document frequencies
    are kept for IDF_WIDTH hashed slots, so the table has a fixed size."""

    idf: np.ndarray | None = None
    name: str = "E2"

    def terms(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        found: dict[str, int] = {}
        row, term, count = [], [], []
        for i, x in enumerate(texts):
            for w, c in Counter(re.findall(r"\w+", normalize_text(x or ""))).items():
                row.append(i)
                term.append(found.setdefault(w, len(found)))
                count.append(c)
        return list(found), np.array(row, np.int64), np.array(term, np.int64), np.array(count, np.int64)

    def scale(self, slots: np.ndarray) -> np.ndarray:
        return self.idf[slots]


def fit_idf(docs: DataFrame) -> WordTfIdf:
    """Slot document frequencies over all rows of ``docs`` (text); at most IDF_WIDTH rows come back."""
    words = F.array_distinct(X.tokens(X.normalize(F.col("text"))))
    slots = docs.select(F.explode(F.array_distinct(F.transform(words, lambda w: F.pmod(X.md5_int(w), F.lit(IDF_WIDTH))))).alias("slot"))
    n = docs.count()
    idf = np.full(IDF_WIDTH, math.log(1 + n) + 1)
    for slot, df in slots.groupBy("slot").count().toPandas().itertuples(index=False):
        idf[slot] = math.log((1 + n) / (1 + df)) + 1
    return WordTfIdf(idf=idf)


def encode(df: DataFrame, embedder: CharGrams, id_col: str = "id") -> DataFrame:
    """(id, vec) of each row."""

    def run(frames):
        memory: dict = {}
        for f in frames:
            for lo in range(0, len(f), 256):
                part = f.iloc[lo : lo + 256]
                yield pd.DataFrame({"id": part["id"], "vec": list(embedder.encode(part["text"].tolist(), memory))})

    return spread(df.select(F.col(id_col).alias("id"), "text")).mapInPandas(run, "id long, vec array<double>")


def l2(v: Column) -> Column:
    """Unit form of a vector; a zero vector stays zero."""
    x = F.transform(v, lambda a: a.cast("double"))
    norm = F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, a: s + a * a))
    return F.transform(x, lambda a: F.when(norm > 0, a / norm).otherwise(F.lit(0.0)))


def norm(v: Column) -> Column:
    return F.sqrt(F.aggregate(F.transform(v, lambda a: a.cast("double")), F.lit(0.0), lambda s, a: s + a * a))
