"""One pass over the train side against blocks of the eval side: shared grams, cosines and
the rule judge's counts of each pair are computed where both records are, and only what a
stage asks for leaves the task. No pair is shuffled. The eval side passes through the
driver in blocks of bounded bytes, of which there is one copy in the session's shared folder
(else a broadcast); a worker holds one block at a time."""

from __future__ import annotations

import atexit
import mmap
import os
import pickle
import re
import uuid
from collections.abc import Iterator
from itertools import chain
from urllib.parse import unquote, urlsplit

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

from ..sources.tables import spread
from .embed import normalize_text

WORDS = re.compile(r"\w+").findall
_DIGITS = re.compile(r"[0-9]+")
#: Bytes of a block of the eval side.
EVAL_BYTES = 64 << 20
#: Train rows that meet a block at once, and rows of a product.
SLICE, PRODUCT = 4096, 512
#: A pair within this of a threshold counts as on it.
SLACK = 1e-9
#: Beyond any error of a product of unit vectors of 1,024 numbers in single precision.
SINGLE = 1e-4
#: Coordinates of the bounds on a cosine, one of them the length of the rest; rows and columns
#: of the part of a product that they leave out; groups of like vectors; and the rows of a
#: block from which bounds pay.
BOUNDS, ROWS, COLUMNS, GROUPS, BOUNDED = (64, 256), 64, 32, 16, 1024
#: Postings and cells that are expanded at once.
_AT_ONCE = 1 << 21
_MIX = np.uint64(0x9E3779B97F4A7C15)


class Hashes(dict):
    """Hash of a word, kept once it has been asked for."""

    def __missing__(self, word: str) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def distinct_grams(words: list[str], k: int, memory: dict[str, int]) -> np.ndarray:
    """Hashes of the distinct k-grams of a record."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    if not isinstance(memory, Hashes):
        memory = Hashes(memory)
    x = np.fromiter(map(memory.__getitem__, words), np.uint64, len(words))
    return np.unique(_mixed(x, k)).view(np.int64)


def gram_sets(lists: list[list[str]], k: int, memory: Hashes) -> list[np.ndarray]:
    """``distinct_grams`` of many records, hashed in one go."""
    n = np.fromiter(map(len, lists), np.int64, len(lists))
    x = np.fromiter(map(memory.__getitem__, chain.from_iterable(lists)), np.uint64, int(n.sum()))
    h, out = _mixed(x, k), []
    for lo, m in zip((np.cumsum(n) - n).tolist(), (n - k + 1).tolist(), strict=True):
        own = np.sort(h[lo : lo + max(0, m)])
        out.append(own[np.r_[True, own[1:] != own[:-1]]].view(np.int64) if own.size else own.view(np.int64))
    return out


def _mixed(x: np.ndarray, k: int) -> np.ndarray:
    """A hash of each run of k of the numbers."""
    n = max(0, x.size - k + 1)
    h = x[:n].copy()
    for i in range(1, k):
        h *= _MIX
        h += x[i : i + n]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return h


class Features:
    """What is computed of a record: grams of k words, a unit vector, masked 3-grams.
    ``bounded``: cosines are asked for from a threshold on, so that blocks bring a sketch."""

    def __init__(self, k: int | None = None, embedder=None, given: bool = False, masked: bool = False, bounded: bool = False):
        self.k, self.embedder, self.given, self.masked = k, embedder, given, masked
        self.bounded = bounded and embedder is not None and not given
        self.column = "vec" if given else "text"

    def of(self, values: list, memory: dict, masked: bool = True) -> dict[str, np.ndarray]:
        masked = masked and self.masked
        out: dict[str, np.ndarray] = {}
        clean = [normalize_text(t or "") for t in values] if not self.given else []
        if self.given:
            out["x"] = np.array(values, float).reshape(len(values), -1)
        elif self.embedder is not None:
            parts = [self.embedder.encode(values[lo : lo + 256], memory.setdefault("terms", {}), clean[lo : lo + 256]) for lo in range(0, len(values), 256)]
            out["x"] = np.vstack(parts)
        words: Hashes = memory.setdefault("words", Hashes())
        if len(words) > 500_000:
            words.clear()
        if self.k:
            lots = (gram_sets([WORDS(t) for t in clean[lo : lo + 256]], self.k, words) for lo in range(0, len(clean), 256))
            out |= _flat("grams", [x for lot in lots for x in lot])
        if masked:
            lists = [WORDS(_DIGITS.sub("0", t)) for t in clean]
            out |= _flat("masked", gram_sets(lists, 3, words))
            out["length"] = np.fromiter(map(len, lists), np.int64, len(lists))
        return out


def _flat(name: str, sets: list[np.ndarray]) -> dict[str, np.ndarray]:
    return {name: np.concatenate(sets) if sets else np.zeros(0, np.int64), f"{name}_n": np.fromiter(map(len, sets), np.int64, len(sets))}


def ranges(starts: np.ndarray, n: np.ndarray) -> np.ndarray:
    """starts[0], starts[0] + 1, ... (n[0] numbers), starts[1], ..."""
    return np.arange(n.sum()) + np.repeat(starts - (np.cumsum(n) - n), n)


class Classes:
    """Records of equal gram sets as one class; records without grams are in none."""

    def __init__(self, flat: np.ndarray, n: np.ndarray, order: np.ndarray):
        """``order``: places of the records in the order in which members are wanted."""
        ends = np.cumsum(n)
        own = order[n[order] > 0]
        names = np.array([xxhash.xxh3_64_intdigest(flat[ends[i] - n[i] : ends[i]]) for i in own.tolist()], np.uint64)
        _, first, label, size = np.unique(names, return_index=True, return_inverse=True, return_counts=True)
        self.members, self.size, self.first = own[np.argsort(label, kind="stable")], size, own[first]
        self.starts = np.cumsum(size) - size
        self.n = n[self.first]
        grams = flat[ranges(ends[self.first] - self.n, self.n)]
        by = np.argsort(grams, kind="stable")
        self.grams, self.owner = grams[by], np.repeat(np.arange(len(size)), self.n)[by].astype(np.int32)

    def expanded(self, at: np.ndarray, most: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """For rows that name classes: place of the row and a member of its class, for each."""
        n = self.size[at] if most is None else np.minimum(self.size[at], most)
        return np.repeat(np.arange(at.size), n), self.members[ranges(self.starts[at], n)]


def coded(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of numbers as the different ones of each row, how many those are, and their places:
    2 bytes a number besides. Vectors of counts hold few different numbers. Without loss."""
    if len(x) > 512:
        return tuple(np.concatenate(c) for c in zip(*(coded(x[lo : lo + 512]) for lo in range(0, len(x), 512)), strict=True))
    bits = np.ascontiguousarray(x).view(np.int64)
    order = np.argsort(bits, axis=1)
    ranked = np.take_along_axis(bits, order, 1)
    new = np.ones(bits.shape, bool)
    new[:, 1:] = ranked[:, 1:] != ranked[:, :-1]
    place = np.empty(bits.shape, np.uint16)
    np.put_along_axis(place, order, (np.cumsum(new, axis=1) - 1).astype(np.uint16), 1)
    return ranked[new].view(x.dtype), new.sum(1), place


def decoded(values: np.ndarray, n: np.ndarray, place: np.ndarray) -> np.ndarray:
    return values[(np.cumsum(n) - n)[:, None] + place]


class Sketch:
    """Bounds on the cosines of a block's vectors: the product of the coordinates along their
    strongest directions and, by Cauchy and Schwarz, that of the lengths of what is left.
    Vectors are ordered by groups of like ones, so that whole parts of a product fall out."""

    def __init__(self, x: np.ndarray, like: Sketch | None = None):
        if like is not None:
            self.name, self.basis, self.centres = like.name, like.basis, like.centres
            y = self.of(x)
        else:
            sample = x[:: max(1, len(x) // 2048)].astype(float)
            self.basis = np.ascontiguousarray(np.linalg.eigh(sample.T @ sample)[1][:, : -BOUNDS[-1] : -1].astype(np.float32))
            self.name, y = uuid.uuid4().hex, self.of(x)
            self.centres = y[0][:: max(1, len(x) // GROUPS)][:GROUPS]
            for _ in range(4):
                group = (y[0] @ self.centres.T).argmax(1)
                self.centres = np.stack([y[0][group == k].mean(0) if (group == k).any() else c for k, c in enumerate(self.centres)])
                self.centres /= np.linalg.norm(self.centres, axis=1, keepdims=True) + 1e-9
        self.order = self.ordered(y)
        self.y = [np.column_stack([v[self.order], np.ones(len(x), np.float32)]) for v in y]

    def of(self, x: np.ndarray) -> list[np.ndarray]:
        """For each bound the coordinates of vectors, and a length that the rest does not exceed."""
        full, square, out = x @ self.basis, np.einsum("ij,ij->i", x, x), []
        for n in BOUNDS:
            part = full[:, : n - 1]
            rest = np.sqrt(np.maximum(0, square - np.einsum("ij,ij->i", part, part)) + np.float32(1e-5))
            out.append(np.column_stack([part, rest]))
        return out

    def ordered(self, y: list[np.ndarray]) -> np.ndarray:
        return np.lexsort((y[0][:, -1], (y[0] @ self.centres.T).argmax(1)))


class Block:
    """Records of the eval side with all that a train record is compared with. Vectors are
    coded while it travels, and stay so: products take ``single``, decisions ``rows``."""

    #: Whether the vectors in single precision travel too.
    keep_single = False

    def __getstate__(self):
        state = dict(vars(self))
        if isinstance(self._x, np.ndarray) and self._x.dtype == np.float64 and 0 < self._x.shape[1] <= 1 << 16:
            state["_x"] = coded(self._x)
        state["_single"] = self.single if self.keep_single else None
        return state

    def __setstate__(self, state):
        vars(self).update(state)
        if isinstance(self._x, tuple):
            values, n, place = self._x
            self._starts = np.cumsum(n) - n

    @property
    def x(self) -> np.ndarray | None:
        return decoded(*self._x) if isinstance(self._x, tuple) else self._x

    @property
    def single(self) -> np.ndarray:
        """The vectors in single precision, in the order of ``places``."""
        if self._single is None and isinstance(self._x, tuple):
            values, _, place = self._x
            values, out = values.astype(np.float32), np.empty(place.shape, np.float32)
            for lo in range(0, len(place), 64):
                at = self.places[lo : lo + 64]
                np.take(values, self._starts[at, None] + place[at], out=out[lo : lo + 64], mode="clip")
            self._single = out
        elif self._single is None:
            self._single = self._x[self.places].astype(np.float32)
        return self._single

    def known(self, grams: np.ndarray) -> np.ndarray:
        """Places of those of the sorted grams that the block may hold, by their first bits."""
        bit = (grams >> self.shift) + (self.seen.size << 2)
        return np.flatnonzero(self.seen[bit >> 3] >> (bit & 7).astype(np.uint8) & 1)

    @property
    def places(self) -> np.ndarray:
        return np.arange(len(self.ids)) if self.sketch is None else self.sketch.order

    def rows(self, at: np.ndarray) -> np.ndarray:
        """Vectors of these places in double precision."""
        if not isinstance(self._x, tuple):
            return self._x[at]
        values, _, place = self._x
        return values[self._starts[at][:, None] + place[at]]

    def __init__(self, ids: np.ndarray, parts: list[dict[str, np.ndarray]], bounded: bool = False, like: Sketch | None = None):
        data = {c: np.concatenate([p[c] for p in parts]) for c in parts[0]}
        self.ids, self._x, self._single = ids, data.get("x"), None
        self.sketch = Sketch(self._x.astype(np.float32), like) if bounded and len(ids) >= BOUNDED else None
        if "grams" in data:
            self.classes = Classes(data["grams"], data["grams_n"], np.argsort(ids, kind="stable"))
            self.least = ids[self.classes.members[self.classes.starts]] if self.classes.size.size else ids[:0]
            self.terms, self.posting = np.unique(self.classes.grams, return_index=True)
            self.posting = np.r_[self.posting, self.classes.grams.size].astype(np.int32)
            self.classes.grams = None  # the terms say the same
            self.shift = np.int64(max(38, 60 - self.terms.size.bit_length()))
            self.seen = np.zeros(1 << int(64 - self.shift), bool)
            self.seen[(self.terms >> self.shift) + (self.seen.size >> 1)] = True
            self.seen = np.packbits(self.seen, bitorder="little")
        if "masked" in data:
            self.masked_n, self.length = data["masked_n"], data["length"]
            self.masked_at = np.cumsum(self.masked_n) - self.masked_n
            self.vocabulary, code = np.unique(data["masked"], return_inverse=True)
            self.masked = code.astype(np.int32)


class Filed:
    """A block in a file that the driver and all executors can read. Its arrays are mapped, not
    read: what is not asked for is not touched, and workers of a machine share the pages."""

    def __init__(self, folder: str, block: Block):
        self.path = os.path.join(folder, f"block-{uuid.uuid4().hex}")
        atexit.register(self.destroy)
        block.keep_single = block._x is not None
        arrays: list[pickle.PickleBuffer] = []
        head = pickle.dumps(block, 5, buffer_callback=arrays.append)
        with open(self.path, "wb") as f:
            pickle.dump((head, [x.raw().nbytes for x in arrays]), f)
            for x in arrays:
                f.write(bytes(-f.tell() % 64))
                f.write(x.raw())

    def __getstate__(self):
        return {"path": self.path}

    @property
    def value(self) -> Block:
        if "_value" not in vars(self):
            with open(self.path, "rb") as f:
                head, sizes = pickle.load(f)
                at, data, arrays = f.tell(), memoryview(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)), []
            for n in sizes:
                at += -at % 64
                arrays.append(data[at : at + n])
                at += n
            self._value = pickle.loads(head, buffers=arrays)
        return self._value

    def destroy(self) -> None:
        atexit.unregister(self.destroy)
        if os.path.exists(self.path):
            os.remove(self.path)


def shared_folder(spark) -> str | None:
    """The session's checkpoint folder where it is one of files: the driver and the executors
    share it by its nature, and one copy there takes the place of one on every machine."""
    at = urlsplit(spark.sparkContext.getCheckpointDir() or "none:")
    folder = unquote(at.path)
    return folder if at.scheme in ("", "file") and os.path.isdir(folder) and os.access(folder, os.W_OK) else None


def blocks(evals: DataFrame, features: Features, most_bytes: int, label: str | None = None) -> list:
    """The eval side (id and what ``features`` takes, and a ``label`` column) in blocks of
    about ``most_bytes``, filed or broadcast. All records are computed in parallel and
    stored; then they pass through the driver partition by partition."""
    columns = ["id", features.column, *([label] if label else [])]
    rows_at_once = max(1, min(512, most_bytes // 8192))

    def run(batches):
        memory: dict = {}
        for b in batches:
            for lo in range(0, b.num_rows, rows_at_once):
                part = b.slice(lo, rows_at_once)
                data = features.of(part.column(1).to_pylist(), memory)
                if "x" in data and 0 < data["x"].shape[1] <= 1 << 16:
                    data["x"] = coded(data["x"])
                yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps((part.column(0).to_numpy(), data, part.column(2).to_pylist() if label else None))], pa.binary())], ["part"])

    spark = evals.sparkSession
    kept = spread(evals.select(*columns)).mapInArrow(run, "part binary").persist()  # not a checkpoint: gone as soon as it is read
    kept.count()
    out, ids, parts, labels, held, like = [], [], [], [], 0, None
    folder = shared_folder(spark)

    def close() -> None:
        nonlocal like
        block = Block(np.concatenate(ids), list(parts), features.bounded, like)
        like = block.sketch or like
        block.labels = list(labels) if label else None
        out.append(Filed(folder, block) if folder else spark.sparkContext.broadcast(block))
        for held_ in (ids, parts, labels):
            held_.clear()

    for r in kept.toLocalIterator():
        own, data, names = pickle.loads(r["part"])
        if isinstance(data.get("x"), tuple):
            data["x"] = decoded(*data["x"])
        size = sum(v.nbytes for v in data.values())
        if parts and held + size > most_bytes:
            close()
            held = 0
        ids.append(own)
        parts.append(data)
        labels += names or []
        held += size
    if parts:
        close()
    kept.unpersist()
    return out


class Slice:
    """Train records that meet a block together."""

    def __init__(self, values: list, features: Features, memory: dict):
        self.size = len(values)
        data = features.of(values, memory, masked=False)
        self.x = data.get("x")
        self.single = self.x.astype(np.float32) if self.x is not None and not features.given else self.x
        if "grams" in data:
            self.classes = Classes(data["grams"], data["grams_n"], np.arange(self.size))
        self.values, self.memory = values, memory
        self.masked: dict[int, tuple[np.ndarray, int]] = {}
        self._turned: tuple = ("",)

    def turned(self, sketch: Sketch) -> tuple[list[np.ndarray], np.ndarray]:
        """Coordinates of the rows for the bounds of a sketch, and their order in its groups."""
        if self._turned[0] != sketch.name:
            x = sketch.of(self.single)
            self._turned = sketch.name, x, sketch.ordered(x)
        return self._turned[1:]

    def judged(self, i: int) -> tuple[np.ndarray, int]:
        """Masked 3-grams and number of words of a record that a pair holds."""
        if i not in self.masked:
            w = WORDS(_DIGITS.sub("0", normalize_text(self.values[i] or "")))
            self.masked[i] = distinct_grams(w, 3, self.memory.setdefault("words", Hashes())), len(w)
        return self.masked[i]


def shared_grams(s: Slice, b: Block, least: float = 0.0) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(class of s, class of b, grams that they share) of all classes that share one; classes
    of s of whose grams the block holds a share below ``least`` may be left out."""
    if not b.terms.size or not s.classes.size.size:
        return
    some = b.known(s.classes.grams)
    at = np.minimum(np.searchsorted(b.terms, s.classes.grams[some]), b.terms.size - 1)
    hit = b.terms[at] == s.classes.grams[some]
    row, term = s.classes.owner[some[hit]].astype(np.int64), at[hit]
    if least > 0:
        some = (np.bincount(row, minlength=s.classes.size.size) >= (least - SLACK) * s.classes.n)[row]
        row, term = row[some], term[some]
    order = np.argsort(row, kind="stable")
    row, term = row[order], term[order]
    first, n, width = b.posting[term].astype(np.int64), np.diff(b.posting)[term].astype(np.int64), b.classes.size.size
    step = max(1, 4 * _AT_ONCE // width)
    for lo in range(0, s.classes.size.size, step):
        a, z = np.searchsorted(row, [lo, lo + step])
        if a == z:
            continue
        ends = np.cumsum(n[a:z])
        if ends[-1] <= min(_AT_ONCE, step * width // 2):  # few: sorted, not counted in all cells
            cell, counts = np.unique(np.repeat(row[a:z], n[a:z]) * width + b.classes.owner[ranges(first[a:z], n[a:z])], return_counts=True)
            yield cell // width, cell % width, counts
            continue
        cuts = [a, *(a + np.searchsorted(ends, np.arange(_AT_ONCE, ends[-1], _AT_ONCE)) + 1).tolist(), z]
        counts = 0
        for p, q in zip(cuts, cuts[1:], strict=False):
            if p < q:
                cells = np.repeat(row[p:q] - lo, n[p:q]) * width + b.classes.owner[ranges(first[p:q], n[p:q])]
                counts = counts + np.bincount(cells, minlength=step * width)
        cell = np.flatnonzero(counts)
        yield cell // width + lo, cell % width, counts[cell]


def jaccards(s: Slice, b: Block, least: float = 0.0) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """With ``least``, pairs of a smaller Jaccard may be missing: it is at most the share of
    the train record's grams that the pair shares."""
    for r, c, inter in shared_grams(s, b, least):
        yield r, c, inter, inter / (s.classes.n[r] + b.classes.n[c] - inter)


def lexical_pairs(s: Slice, b: Block, asked) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(row, place in the block, inter, score) of the pairs that ``asked`` (inter, n of the
    train record, n of the eval record) scores from its threshold on. A third member is the
    least share of the train record's grams that such a pair has."""
    score, tau, *least = asked
    for r, c, inter in shared_grams(s, b, *least):
        v = score(inter, s.classes.n[r], b.classes.n[c])
        ok = v >= tau - SLACK
        r, c, inter, v = r[ok], c[ok], inter[ok], v[ok]
        at, row = s.classes.expanded(r)
        again, place = b.classes.expanded(c[at])
        yield row[again], place, inter[at][again], v[at][again]


def products(s: Slice, b: Block, least: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(places in the block, rows, cosines of each of those places with each of those rows),
    in single precision where the slice has it. With ``least``, a number for each row, cosines
    below it may be left out: a part of the product is, if the bounds of all its pairs are."""
    if least is None or b.sketch is None:
        other = b.x if s.single is s.x else b.single
        places = np.arange(len(other)) if s.single is s.x else b.places
        for lo in range(0, s.size, PRODUCT):
            yield places, np.arange(lo, min(s.size, lo + PRODUCT)), other @ s.single[lo : lo + PRODUCT].T
        return
    (x, order), n = s.turned(b.sketch), len(b.ids)
    floor, space = np.clip(least - SINGLE, -3, 3).astype(np.float32), np.empty(n * ROWS, np.float32)
    over = lambda k, row: np.column_stack([x[k][row], -floor[row]])  # noqa: E731  by how much a bound is over the floor
    for lo in range(0, s.size, PRODUCT):
        rows = order[lo : lo + PRODUCT]
        most = over(0, rows) @ b.sketch.y[0].T
        for at in range(0, rows.size, ROWS):
            row = rows[at : at + ROWS]
            tiles = np.flatnonzero(np.logical_or.reduceat(most[at : at + ROWS].max(0) >= 0, np.arange(0, n, COLUMNS)))
            for k in range(1, len(BOUNDS) + 1):
                if not tiles.size:
                    break
                y, own = (b.sketch.y[k], over(k, row)) if k < len(BOUNDS) else (b.single, s.single[row])
                cut = np.flatnonzero(np.diff(tiles) > 1) + 1
                out, done = space[: n * row.size].reshape(n, row.size), 0
                for p, q in zip(tiles[np.r_[0, cut]].tolist(), tiles[np.r_[cut - 1, -1]].tolist(), strict=True):
                    part = y[p * COLUMNS : (q + 1) * COLUMNS]
                    np.matmul(part, own.T, out=out[done : done + len(part)])
                    done += len(part)
                if k < len(BOUNDS):
                    tiles = tiles[np.maximum.reduceat(out[:done].max(1), np.arange(0, done, COLUMNS)) >= 0]
            else:
                place = ranges(tiles * COLUMNS, np.minimum(COLUMNS, n - tiles * COLUMNS))
                yield b.places[place], row, out[:done]


def near_pairs(s: Slice, b: Block, tau: float, scores: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row, place in the block, cosine) of the pairs from tau on. A product in single
    precision finds them with a margin, double precision decides. Without ``scores`` only
    pairs within that margin are decided so, and the cosines are not exact."""
    least = tau - SLACK - (0 if s.single is s.x else SINGLE)
    for place, row, c in products(s, b, np.full(s.size, least)):
        j, i = np.divmod(np.flatnonzero(c.reshape(-1) >= c.dtype.type(least)), row.size)
        for at in range(0, i.size, 4096):
            p, q, v = row[i[at : at + 4096]], place[j[at : at + 4096]], c[j[at : at + 4096], i[at : at + 4096]]
            if s.single is not s.x:
                v = v.astype(float)
                open_ = slice(None) if scores else np.flatnonzero(v < tau - SLACK + SINGLE)
                v[open_] = np.einsum("ij,ij->i", s.x[p[open_]], b.rows(q[open_]))
            ok = v >= tau - SLACK
            yield p[ok], q[ok], v[ok]


class BestLexical:
    """Highest Jaccard of each row and its smallest eval id; with ``tau``, none below it."""

    def __init__(self, s: Slice, tau: float = 0.0):
        self.s, self.tau, n = s, tau, s.classes.size.size
        self.j, self.e = np.zeros(n), np.full(n, np.iinfo(np.int64).max)

    def step(self, b: Block) -> None:
        for r, c, _, j in jaccards(self.s, b, self.tau):
            if self.tau:
                ok = j >= self.tau - SLACK
                r, c, j = r[ok], c[ok], j[ok]
            order = np.lexsort((b.least[c], -j, r))
            order = order[np.r_[True, r[order][1:] != r[order][:-1]][: r.size]]
            r, j, e = r[order], j[order], b.least[c[order]]
            ok = (j > self.j[r]) | ((j == self.j[r]) & (e < self.e[r]))
            self.j[r[ok]], self.e[r[ok]] = j[ok], e[ok]

    def rows(self) -> tuple[pa.Array, pa.Array]:
        j, e, some = np.zeros(self.s.size), np.zeros(self.s.size, np.int64), np.zeros(self.s.size, bool)
        at, row = self.s.classes.expanded(np.arange(self.j.size))
        j[row], e[row], some[row] = self.j[at], self.e[at], self.j[at] > 0
        return pa.array(e, mask=~some), pa.array(j, mask=~some if self.tau else None)


class TopLexical:
    """The ``most`` highest Jaccards of each row, ties to smaller eval ids."""

    def __init__(self, s: Slice, most: int):
        self.s, self.most = s, most
        self.r, self.e, self.j = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)

    def _first(self, r: np.ndarray, e: np.ndarray, j: np.ndarray) -> np.ndarray:
        order = np.lexsort((e, -np.round(j, 9), r))
        new = np.flatnonzero(np.r_[True, r[order][1:] != r[order][:-1]]) if r.size else np.zeros(0, np.int64)
        rank = np.arange(r.size) - np.repeat(new, np.diff(np.r_[new, r.size]))
        return order[rank < self.most]

    def step(self, b: Block) -> None:
        for r, c, _, j in jaccards(self.s, b):
            at = self._first(r, b.least[c], j)
            row, place = b.classes.expanded(c[at], self.most)
            r, e, j = np.r_[self.r, r[at][row]], np.r_[self.e, b.ids[place]], np.r_[self.j, j[at][row]]
            at = self._first(r, e, j)
            self.r, self.e, self.j = r[at], e[at], j[at]

    def rows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """row, eval id, rank from 1, Jaccard."""
        new = np.flatnonzero(np.r_[True, self.r[1:] != self.r[:-1]]) if self.r.size else np.zeros(0, np.int64)
        rank = np.arange(self.r.size) - np.repeat(new, np.diff(np.r_[new, self.r.size])) + 1
        at, row = self.s.classes.expanded(self.r)
        return row, self.e[at], rank[at], self.j[at]


class BestCosine:
    """Highest cosine of each row; nearly equal ones are ties, which the smallest id wins.
    With ``tau``, none below it."""

    def __init__(self, s: Slice, tau: float | None = None):
        self.s, self.tau = s, tau
        self.top = np.full(s.size, -np.inf if tau is None else tau - SLACK + (0 if s.single is s.x else SINGLE))
        self.r, self.e, self.c = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        self.zero, self.least = ~s.x.any(1), None

    def step(self, b: Block) -> None:
        s, single = self.s, self.s.single is not self.s.x
        self.least = min(b.ids.min(), b.ids.min() if self.least is None else self.least)
        margin = 2 * SINGLE if single else SLACK
        for place, row, c in products(s, b, None if self.tau is None else np.where(self.zero, np.inf, self.top - margin)):
            top = self.top[row] = np.maximum(self.top[row], c.max(0))
            floor = np.where(self.zero[row], np.inf, top - margin)
            j, i = np.divmod(np.flatnonzero((c >= floor.astype(c.dtype)).reshape(-1)), row.size)
            p, q = row[i], place[j]
            v = np.concatenate([np.einsum("ij,ij->i", s.x[p[at : at + 4096]], b.rows(q[at : at + 4096])) for at in range(0, p.size, 4096)]) if single and p.size else c[j, i].astype(float)
            self.r, self.e, self.c = np.r_[self.r, p], np.r_[self.e, b.ids[q]], np.r_[self.c, v]
        best = np.full(s.size, -np.inf)
        np.maximum.at(best, self.r, self.c)
        ok = self.c >= best[self.r] - SLACK
        self.r, self.e, self.c, self.best = self.r[ok], self.e[ok], self.c[ok], best

    def rows(self) -> tuple[pa.Array, pa.Array]:
        """Nulls where there is no eval record, or none from ``tau`` on."""
        if self.least is None:
            return pa.nulls(self.s.size, pa.int64()), pa.nulls(self.s.size, pa.float64())
        e = np.full(self.s.size, np.iinfo(np.int64).max)
        np.minimum.at(e, self.r, self.e)
        none = np.zeros(self.s.size, bool) if self.tau is None else self.zero | (self.best < self.tau - SLACK)
        return pa.array(np.where(self.zero, self.least, e), mask=none), pa.array(np.where(self.zero, 0.0, self.best), mask=none)


def judge(s: Slice, b: Block, row: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """contained and length_ratio of pairs in the order of their rows."""
    contained, ratio = np.zeros(row.size), np.ones(row.size)
    held = np.zeros(b.vocabulary.size + 1, np.uint8)
    new = np.flatnonzero(np.r_[True, row[1:] != row[:-1]]) if row.size else np.zeros(0, np.int64)
    for lo, hi in zip(new.tolist(), np.r_[new[1:], row.size].tolist(), strict=True):
        grams, length = s.judged(int(row[lo]))
        at = np.minimum(np.searchsorted(b.vocabulary, grams), max(0, b.vocabulary.size - 1))
        own = at[b.vocabulary[at] == grams] if b.vocabulary.size else at[:0]
        held[own] = 1
        for k in range(lo, hi, 256):
            j = place[k : min(hi, k + 256)]
            n = b.masked_n[j]
            some = n > 0
            inter = np.zeros(j.size)
            if some.any():
                m = n[some]
                inter[some] = np.add.reduceat(held[b.masked[ranges(b.masked_at[j[some]], m)]], np.cumsum(m) - m, dtype=np.int64)
            small, most = np.minimum(n, grams.size), np.maximum(b.length[j], length)
            contained[k : k + j.size] = np.divide(inter, small, out=np.zeros(j.size), where=small > 0)
            ratio[k : k + j.size] = np.divide(np.minimum(b.length[j], length), most, out=np.ones(j.size), where=most > 0)
        held[own] = 0
    return contained, ratio


def run(train: DataFrame, shared: list, features: Features, work, schema: str, keys: tuple[str, ...] = ("id",)) -> DataFrame:
    """``work(slice, blocks)`` gives (places of rows or None for all, arrays) once or more;
    its arrays stand behind the key columns of those rows."""
    names = [c.strip().split(" ")[0] for c in schema.split(",")]

    class Each:
        """The blocks, as often as they are asked for."""

        def __iter__(self):
            for b in shared:
                yield b.value
                if len(shared) > 1:
                    vars(b).pop("_value", None)  # one block at a time in memory

    def body(batches):
        memory: dict = {}
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE):
                part = batch.slice(lo, SLICE)
                own = Slice(part.column(len(keys)).to_pylist(), features, memory)
                own.keys = part.select(list(range(len(keys))))
                for row, arrays in work(own, Each()):
                    own = [part.column(k) if row is None else part.column(k).take(pa.array(row)) for k in range(len(keys))]
                    yield pa.RecordBatch.from_arrays([*own, *(x if isinstance(x, pa.Array) else pa.array(x) for x in arrays)], names)

    return spread(train.select(*keys, features.column)).mapInArrow(body, schema)
