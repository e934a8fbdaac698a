"""Byte-level BPE by longest matches and backtracking.

Bytes are read as Latin-1 characters so that an Aho-Corasick automaton over the
vocabulary finds the longest token at every place in one pass. Encoding walks a piece
with the longest token first and takes a shorter one, or goes back, where two adjacent
tokens could not stand side by side in the result of the merges. That compatibility
depends on the two tokens alone and is memoised; each place is given up at most once, so
the time is linear in the piece. The ids are those of merging by ascending rank.
"""

from __future__ import annotations

import base64
import hashlib
import re
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_slices, texts_of

#: Pieces and words whose ids a worker remembers at once, and the length of the longest of them.
MEMORY, LONGEST = 600_000, 64


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class BytePairEncoder:
    def __init__(self, ranks: dict[bytes, int]):
        if any(bytes([b]) not in ranks for b in range(256)):
            raise ValueError("a byte-level vocabulary holds every byte")
        self.ranks = ranks
        self.bytes_of = {r: t for t, r in ranks.items()}
        self.beyond = max(ranks.values()) + 1
        self.halves: dict[int, tuple[int, int] | None] = {}
        self.side_by_side: dict[tuple[int, int], bool] = {}
        self.automaton = ahocorasick.Automaton()
        reachable = set()
        # a token counts only if merging its own bytes gives it back
        for token, rank in ranks.items():
            if len(token) == 1:
                self.halves[rank] = None
            else:
                parts = self._merge(token, rank)
                if len(parts) != 2:
                    continue
                self.halves[rank] = (ranks[parts[0]], ranks[parts[1]])
            reachable.add(token)
            self.automaton.add_word(token.decode("latin-1"), (len(token), rank))
        self.automaton.make_automaton()
        self.shorter: dict[int, int | None] = {}
        for token in reachable:
            n = next((n for n in range(len(token) - 1, 0, -1) if token[:n] in reachable), 0)
            self.shorter[ranks[token]] = ranks[token[:n]] if n else None

    def _merge(self, piece: bytes, below: int) -> list[bytes]:
        """Merges of rank under ``below``, lowest rank and leftmost first."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 1:
            best, at = min((self.ranks.get(parts[i] + parts[i + 1], below), i) for i in range(len(parts) - 1))
            if best >= below:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """What stands at that end of a token while it is being built: (part, rank of the
        merge that takes the part away); the whole token is never taken away."""
        out, last = [], self.beyond
        while True:
            out.append((token, last))
            if self.halves[token] is None:
                return out
            last, token = token, self.halves[token][side]

    def compatible(self, left: int, right: int) -> bool:
        """Can the tokens be neighbours in a result? Not if, at some moment of the merges,
        the part at the left one's end and the part at the right one's start make a token
        whose merge comes before either part is taken away. Equal ranks go leftmost first."""
        key = (left, right)
        known = self.side_by_side.get(key)
        if known is None:
            known = True
            for x, x_gone in self._edge(left, 1):
                for y, y_gone in self._edge(right, 0):
                    rank = self.ranks.get(self.bytes_of[x] + self.bytes_of[y])
                    if rank is not None and rank < x_gone and rank <= y_gone:
                        known = False
                        break
                if not known:
                    break
            if len(self.side_by_side) > 4 * MEMORY:
                self.side_by_side.clear()
            self.side_by_side[key] = known
        return known

    def encode_piece(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        n = len(piece)
        longest = [0] * n
        for end, (size, rank) in self.automaton.iter(piece.decode("latin-1")):
            longest[end - size + 1] = rank
        # the automaton reports matches by their end: the last one written for a start is its longest
        sizes, shorter, compatible = self.bytes_of, self.shorter, self.compatible
        dead = bytearray(n + 1)
        tokens: list[int] = []
        at, token = 0, longest[0]
        while True:
            end = at + len(sizes[token])
            if not dead[end] and (not tokens or compatible(tokens[-1], token)):
                tokens.append(token)
                at = end
                if at == n:
                    return tokens
                token = longest[at]
                continue
            token = shorter[token]
            while token is None:
                dead[at] = 1
                last = tokens.pop()
                at -= len(sizes[last])
                token = shorter[last]

    def encode_text(self, text: str, pattern: regex.Pattern) -> list[int]:
        return [i for m in pattern.findall(text) for i in self.encode_piece(m.encode())]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


#: A space whose neighbours on both sides are space or an end: there a cut before spaces could split a run.
_RUN = re.compile(r"\s (?:\s|$)")


class _Words(dict):
    """Text between cuts -> its ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, encoder: BytePairEncoder, pattern: str):
        super().__init__()
        self.encoder, self.find, self.pieces = encoder, regex.compile(pattern).findall, {}

    def __missing__(self, word: str) -> bytes:
        pieces, out = self.pieces, []
        for p in self.find(word):
            ids = pieces.get(p)
            if ids is None:
                ids = np.array(self.encoder.encode_piece(p.encode()), "<u4").tobytes()
                if len(pieces) >= MEMORY // 2:
                    pieces.clear()
                if len(p) <= LONGEST:
                    pieces[p] = ids
            out.append(ids)
        if len(self) >= MEMORY:
            self.clear()
        made = b"".join(out)
        if len(word) <= LONGEST:
            self[word] = made
        return made

    def encode(self, text: str) -> bytes:
        """Each space after something else begins a piece, so texts are cut before spaces."""
        if _RUN.search(text):
            return b"".join([self[p] for p in self.find(text)])
        first, *rest = text.split(" ")
        get = self.__getitem__
        return get(first) + b"".join([get(" " + w) for w in rest])


@lru_cache(maxsize=2)
def _words(path: str, pattern: str) -> _Words:
    return _Words(BytePairEncoder(read_ranks(path)), pattern)


def encode_decode(docs: DataFrame, path: str, pattern: str, with_ids: bool = False) -> DataFrame:
    """For each row (null text: empty): doc_id, n_tokens, ids_sha256, decoded_sha256 and, if
    asked for, ids. ``path``: a rank file each worker can read; ``pattern``: what splits a
    text before the merges, as for the library that the file is for."""

    def run(batches):
        words = _words(path, pattern)
        decode, sha = words.encoder.bytes_of.__getitem__, hashlib.sha256
        for b in text_slices(batches):
            n, digests, decoded, ids = [], [], [], []
            for t in texts_of(b):
                own = words.encode(t)
                n.append(len(own) // 4)
                digests.append(sha(own).hexdigest())
                numbers = np.frombuffer(own, "<u4").tolist()
                decoded.append(sha(b"".join(map(decode, numbers))).hexdigest())
                if with_ids:
                    ids.append(numbers)
            cols = [b.column(0), pa.array(n, pa.int64()), pa.array(digests, pa.string()), pa.array(decoded, pa.string())]
            yield pa.RecordBatch.from_arrays(cols + [pa.array(ids, pa.list_(pa.int64()))] * with_ids, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", *["ids"] * with_ids])

    rows = docs.select("doc_id", "text")
    return rows.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<long>" * with_ids)


def decode_ids(rows: DataFrame, path: str, ids_col: str = "ids") -> DataFrame:
    """Adds ``decoded`` (bytes; null ids: null) to rows with an array of ids."""

    @F.pandas_udf("binary")
    def decoded(col):
        encoder = _words(path, r"[\s\S]+").encoder
        return col.map(lambda ids: None if ids is None else encoder.decode(list(ids)))

    return rows.withColumn("decoded", decoded(F.col(ids_col)))
