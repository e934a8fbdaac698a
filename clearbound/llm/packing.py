"""Packing token pieces into sequences by minimum bin slack.

A bin is seeded with the longest piece left and filled by the combination of available
lengths that leaves the least slack, found by subset sums over a bitset; the same bin is
repeated while the lengths last. That needs the number of pieces of each length only, at
most one number for each token of a sequence, so the plan is made on the driver from a
bounded histogram. Pieces then take their places in the plan by their rank among those of
their length, which is counted in parallel.
"""

from __future__ import annotations

import re
import unicodedata
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, gathered, number_within, text_slices, texts_of

#: Words whose ids a worker remembers at once, and the length of the longest of them.
MEMORY, LONGEST = 900_000, 64

# Characters on which a word's ids do not depend on its neighbours, whose case and form
# need no context and whose class is the same for re and the tokenizer: any other text is
# given to the tokenizer whole.
_PLAIN = re.compile("[^\x20-\x7e\t\n\r\xa1-\xa9\xab-\xb1\xb4\xb6-\xb8\xbb\xbf-įĲ-˿‐-‧€]")
_PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+")


def _byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: visible Latin-1
    characters for themselves, the other bytes in order from 256 on."""
    seen = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in seen]
    return [chr(b) if b in seen else chr(256 + rest.index(b)) for b in range(256)]


class Tokenizer:
    """Ids of whole texts by the tokenizers library, a word at a time where that is the same."""

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer as Library

        self.library = Library.from_file(path)
        self.library.encode_special_tokens = True  # their strings in a text are ordinary text
        self.known: dict[str, bytes] = {}
        self.pieces: dict[str, bytes] = {}
        self.letters = _byte_letters()
        self.by_word = self._splits_at_blanks()

    def _splits_at_blanks(self) -> bool:
        """Does the tokenizer drop blanks and treat these pieces apart? Asked of it, not assumed."""
        probe = ["ab, c'd it's 12 x_y !_! «É» don't €5", "WORLD's End"]
        try:
            return self._ids(probe) == [b"".join(map(self._word, t.lower().split())) for t in probe]
        except Exception:  # noqa: BLE001  a model without such pieces: whole texts then
            return False

    def _ids(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _word(self, word: str) -> bytes:
        out = []
        for p in _PIECE.findall(word):
            ids = self.pieces.get(p)
            if ids is None:
                own = p if p.isascii() else "".join([self.letters[b] for b in p.encode()])
                ids = np.array([t.id for t in self.library.model.tokenize(own)], "<u4").tobytes()
                if len(self.pieces) > MEMORY // 2:
                    self.pieces.clear()
                if len(p) <= LONGEST:
                    self.pieces[p] = ids
            out.append(ids)
        return b"".join(out)

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        plain = [self.by_word and not _PLAIN.search(t) for t in texts]
        words = [t.lower().split() if p else None for t, p in zip(texts, plain, strict=True)]
        known = self.known
        if len(known) > MEMORY:
            known.clear()
        make, long = self._word, {}
        for w in set().union(*(w for w in words if w)).difference(known):
            (known if len(w) <= LONGEST else long)[w] = make(w)
        get = (lambda w: known[w] if w in known else long[w]) if long else known.__getitem__
        rest = iter(self._ids([t for t, w in zip(texts, words, strict=True) if w is None]))
        return [b"".join(map(get, w)) if w is not None else next(rest) for w in words]


@lru_cache(maxsize=2)
def _tokenizer(path: str) -> Tokenizer:
    return Tokenizer(path)


def tokenise(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """Pieces (doc_id, piece, start, length, ids_crc32) of each row's ids followed by
    ``end_id``; rows longer than ``capacity`` are cut, others are one piece. Null: empty."""

    def run(batches):
        tokenizer, end = _tokenizer(path), np.array([end_id], "<u4").tobytes()
        for b in text_slices(batches):
            row, piece, start, length, crc = [], [], [], [], []
            for k, ids in enumerate(tokenizer.encode(texts_of(b))):
                ids += end
                for i, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    row.append(k)
                    piece.append(i)
                    start.append(at // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, piece int, start long, length long, ids_crc32 long")


def fullest(counts: dict[int, int], room: int) -> list[int]:
    """Lengths, each at most as often as it is available, whose sum is the largest that
    ``room`` holds. Longer ones are tried first and the search stops at a full bin."""
    reach, mask, states = 1, (1 << (room + 1)) - 1, []
    for length in sorted((n for n, c in counts.items() if c and n <= room), reverse=True):
        left = min(counts[length], room // length)
        step = 1
        while left:  # copies in powers of two: any number up to all of them
            take = min(step, left)
            grown = (reach | (reach << (take * length))) & mask
            if grown != reach:
                states.append((length, take, reach))
                reach = grown
            left -= take
            step *= 2
        if reach >> room & 1:
            break
    sum_ = reach.bit_length() - 1
    chosen: list[int] = []
    for length, take, before in reversed(states):
        if not before >> sum_ & 1:
            chosen += [length] * take
            sum_ -= take * length
    return chosen


def plan_bins(counts: dict[int, int], capacity: int) -> list[tuple[list[int], int]]:
    """Bins as (lengths, how many such bins), longest seeds first."""
    left = {n: c for n, c in counts.items() if c}
    plan: list[tuple[list[int], int]] = []
    while left:
        seed = max(left)
        left[seed] -= 1
        own = [seed, *fullest(left, capacity - seed)]
        left[seed] += 1
        uses = {n: own.count(n) for n in own}
        times = min(left[n] // k for n, k in uses.items())
        for n, k in uses.items():
            left[n] -= times * k
            if not left[n]:
                del left[n]
        plan.append((own, times))
    return plan


def pack(pieces: DataFrame, capacity: int = 2048) -> DataFrame:
    """Adds sequence_id and offset (columns of these names are replaced) to rows with
    ``length`` (1 to capacity) and the order columns doc_id, piece. ``pieces`` should be cut
    already: it is read four times."""
    pieces = pieces.drop("sequence_id", "offset")
    counts = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}
    plan = plan_bins(counts, capacity)
    # for each length: from which rank on a bin kind holds it, and where it stands there
    bounds: dict[int, list[tuple[int, int, int, int]]] = {n: [] for n in counts}
    ranks, first = dict.fromkeys(counts, 0), 0
    for own, times in plan:
        at = 0
        places: dict[int, list[int]] = {}
        for n in own:
            places.setdefault(n, []).append(at)
            at += n
        for n, offsets in places.items():
            for offset in offsets:
                bounds[n].append((ranks[n], first, offset, times))
                ranks[n] += times
        first += times
    table = {n: tuple(np.array(c, np.int64) for c in zip(*rows, strict=True)) for n, rows in bounds.items()}

    def place(batches):
        for b in gathered(batches, 1 << 16):
            length, rank = b.column("length").to_numpy(), b.column("_number").to_numpy()
            sequence, offset = np.zeros(length.size, np.int64), np.zeros(length.size, np.int64)
            for n in np.unique(length).tolist():
                own = np.flatnonzero(length == n)
                ranks, firsts, offsets, _ = table[n]
                k = np.searchsorted(ranks, rank[own], side="right") - 1
                sequence[own], offset[own] = firsts[k] + rank[own] - ranks[k], offsets[k]
            yield pa.RecordBatch.from_arrays([*(c for c, f in zip(b.columns, b.schema, strict=True) if f.name != "_number"), pa.array(sequence), pa.array(offset)], [*(f.name for f in b.schema if f.name != "_number"), "sequence_id", "offset"])

    numbered = number_within(pieces, "length", ["doc_id", "piece", "ids_crc32"], "_number").select(*pieces.columns, "_number")
    kinds = ", ".join(f"`{n}` {t}" for n, t in pieces.dtypes)
    return numbered.mapInArrow(place, f"{kinds}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str, capacity: int = 2048) -> DataFrame:
    return pack(cut(tokenise(docs, path, capacity)), capacity)
