"""Exact substring dedup with fixed-block anchors.

Reference blocks are the non-overlapping blocks of ``block`` words of every document;
every rolling window of ``block`` words of every document probes them. With
2 * block - 1 <= window each repeat of ``window`` words holds a whole reference block of
its earlier copy, so anchors miss none. Hits are then extended: the windows of
``window`` words around the hits are compared by 96-bit hashes, and runs of
windows that start in a document of smaller id are the maximal exact repeats removed.

Rows of the exchanges are not windows but blobs: a task sorts the windows of some
megabytes of text, keeps one entry for each of its hashes (a hash that it meets twice is
decided in place), and sends each bucket of hashes one blob of byte planes. So a passage
in a third of all texts is one entry a task, whatever its count, and what moves is about
eight bytes a word. Hits return by buckets of documents, where they meet their texts.

Null and empty texts have no words. Rows of one doc_id are never compared with one
another; rows without doc_id keep all their words and are compared with none.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, id_bucket, id_bucket_np, ordered_bits, pack, pack_sorted, raw_texts_of, runs, shuffle_partitions, signed_ids, text_slices, unpack, unpack_sorted

#: Text bytes whose windows one sort takes.
SORT_BYTES = 6 << 20
#: Text bytes whose windows one bucket of hashes, or whose texts one bucket of ids, holds:
#: more text means more buckets, not larger ones.
TASK_BYTES = 24 << 20
_BASES = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F))
_SENT = "key int, kind int, h binary, g binary, d binary, p binary, ids binary"
_HITS = "part int, ids binary, n binary, p binary"


class Chunk:
    """Word hashes of several documents in one array. row: which row of the chunk a word is of."""

    def __init__(self, texts: list[bytes]):
        words = [t.split() for t in texts]
        n = np.fromiter(map(len, words), np.int64, len(words))
        h = xxhash.xxh3_64_intdigest
        self.x = np.fromiter((h(w) for ws in words for w in ws), np.uint64, int(n.sum()))
        self.n, self.start = n, np.cumsum(n) - n
        self.row = np.repeat(np.arange(len(texts)), n)
        self.pos = np.arange(self.x.size) - self.start[self.row]

    def windows(self, k: int, base: np.uint64) -> np.ndarray:
        """Hash of the k words from each place on (of no meaning near a document's end)."""
        m = self.x.size - k + 1
        if m <= 0:
            return np.zeros(0, np.uint64)
        h = self.x[:m].copy()
        for i in range(1, k):
            h *= base
            h += self.x[i : i + m]
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(32)
        return h

    def whole(self, k: int) -> np.ndarray:
        """Places where k words of one document begin."""
        m = max(0, self.x.size - k + 1)
        return np.flatnonzero(self.pos[:m] <= (self.n[self.row[:m]] - k))


def _hit_rows(ids: np.ndarray, pos: np.ndarray, parts: int) -> Iterator[tuple]:
    """(part, ids, n, p) blobs of hits (id, place), by bucket of id."""
    if not ids.size:
        return
    part = id_bucket_np(ids, parts)
    order = np.lexsort((pos, ids, part))
    ids, pos, part = ids[order], pos[order], part[order]
    for s, n in zip(*runs(part), strict=True):
        own, where = ids[s : s + n], pos[s : s + n]
        at, counts = runs(own)
        yield int(part[s]), pack_sorted(ordered_bits(own[at])), pack(counts), pack(where)


def _hits_of(rows: pa.Table) -> dict[int, np.ndarray]:
    """doc_id -> places, of the blobs of one part."""
    out: dict[int, list[np.ndarray]] = {}
    for ids, n, p in zip(*(rows.column(c).to_pylist() for c in ("ids", "n", "p")), strict=True):
        counts, where = unpack(n).astype(np.int64), unpack(p).astype(np.int64)
        for i, piece in zip(signed_ids(unpack_sorted(ids)).tolist(), np.split(where, np.cumsum(counts)[:-1]), strict=True):
            out.setdefault(i, []).append(piece)
    return {i: np.unique(np.concatenate(v)) for i, v in out.items()}


def _send(h: np.ndarray, g: np.ndarray | None, d: np.ndarray, p: np.ndarray, ids: np.ndarray, buckets: int) -> Iterator[tuple]:
    """Blobs of entries by bucket of hash. h ascending; d: index into ids (ascending)."""
    if not h.size:
        return
    key = ((h >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)
    for s, n in zip(*runs(key), strict=True):
        own, index = np.unique(d[s : s + n], return_inverse=True)
        yield int(key[s]), 0, pack_sorted(h[s : s + n]), pack(g[s : s + n]) if g is not None else b"", pack(index), pack(p[s : s + n]), pack_sorted(ids[own])


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


_SENT_TYPE = pa.schema([("key", pa.int32()), ("kind", pa.int32()), *((c, pa.binary()) for c in ("h", "g", "d", "p", "ids"))])
_HITS_TYPE = pa.schema([("part", pa.int32()), ("ids", pa.binary()), ("n", pa.binary()), ("p", pa.binary())])


def _relay(rows: Iterator[tuple], buckets: int) -> Iterator[tuple]:
    """Hits that are already decided, as rows of the exchange (kind 1), any bucket."""
    for part, ids, n, p in rows:
        yield part % buckets, 1, p, n, b"", part.to_bytes(4, "little"), ids


def _entries(rows: pa.Table):
    """(h, g, id bits, p) of the kind-0 blobs of one bucket, and its decided hits."""
    h, g, i, p, done = [], [], [], [], []
    for kind, bh, bg, bd, bp, bi in zip(*(rows.column(c).to_pylist() for c in ("kind", "h", "g", "d", "p", "ids")), strict=True):
        if kind:
            done.append((int.from_bytes(bp, "little"), bi, bg, bh))
            continue
        h.append(unpack_sorted(bh))
        g.append(unpack(bg) if bg else np.zeros(0, np.uint64))
        i.append(unpack_sorted(bi)[unpack(bd).astype(np.int64)])
        p.append(unpack(bp).astype(np.int64))
    join = lambda xs: np.concatenate(xs) if xs else np.zeros(0, np.uint64)
    return join(h), join(g), join(i), join(p).astype(np.int64), done


def _anchors(block: int, buckets: int, parts: int):
    """First exchange, sending side: rolling windows of ``block`` words; those that start
    at a multiple of ``block`` are the index."""

    def run(batches):
        for b in text_slices(batches, limit=SORT_BYTES):
            b = b.filter(b.column(0).is_valid())
            if not b.num_rows:
                continue
            ids = ordered_bits(b.column(0).to_numpy(zero_copy_only=False))
            by_id = np.argsort(ids, kind="stable")
            ids, texts = ids[by_id], raw_texts_of(b)
            c = Chunk([texts[i] for i in by_id])
            at = c.whole(block)
            h = c.windows(block, _BASES[0])[at] & ~np.uint64(0xFFFF) if at.size else np.zeros(0, np.uint64)
            order = np.argsort(h, kind="stable")
            h, at = h[order], at[order]
            starts, n = runs(h)
            aligned = c.pos[at] % block == 0
            indexed = np.logical_or.reduceat(aligned, starts) if starts.size else aligned[:0]
            again = np.repeat(n > 1, n)
            # entry: 4 * place + 2 * (decided here) + 1 * (in the index)
            p = c.pos[at[starts]] * 4 + 2 * (n > 1) + indexed
            rows = list(_send(h[starts] >> np.uint64(0), None, c.row[at[starts]], p, ids, buckets))
            rows += _relay(_hit_rows(signed_ids(ids[c.row[at[again]]]), c.pos[at[again]], parts), buckets)
            if rows:
                yield _batch(rows, _SENT_TYPE)

    return run


def _match_anchors(parts: int):
    def run(rows: pa.Table) -> pa.Table:
        h, _, ids, p, done = _entries(rows)
        order = np.argsort(h, kind="stable")
        h, ids, p = h[order], ids[order], p[order]
        starts, n = runs(h)
        out = done
        if starts.size:
            shared = (n > 1) & np.logical_or.reduceat((p & 1).astype(bool), starts)
            take = np.repeat(shared, n) & ((p & 2) == 0)
            out = done + list(_hit_rows(signed_ids(ids[take]), p[take] >> 2, parts))
        return pa.Table.from_batches([_batch(out, _HITS_TYPE)] if out else [], _HITS_TYPE)

    return run


def _extend(block: int, window: int, buckets: int, parts: int):
    """Second exchange, sending side: the windows of ``window`` words that hold a hit."""

    def run(docs: pa.Table, hits: pa.Table) -> pa.Table:
        places = _hits_of(hits)
        out: list[tuple] = []
        if places and docs.num_rows:
            for b in text_slices(docs.to_batches(), limit=SORT_BYTES):
                keep = [k for k, i in enumerate(b.column(0).to_pylist()) if i in places]
                if not keep:
                    continue
                b = b.take(pa.array(keep))
                ids = ordered_bits(b.column(0).to_numpy(zero_copy_only=False))
                by_id = np.argsort(ids, kind="stable")
                ids, texts = ids[by_id], raw_texts_of(b)
                c = Chunk([texts[i] for i in by_id])
                near = np.zeros(c.x.size + 1, np.int64)
                for row, i in enumerate(signed_ids(ids).tolist()):
                    p = places[i]
                    p = p[p < c.n[row]]
                    np.add.at(near, c.start[row] + np.maximum(0, p - (window - block)), 1)
                    np.add.at(near, c.start[row] + p + 1, -1)
                at = c.whole(window)
                at = at[np.cumsum(near)[at] > 0]
                if not at.size:
                    continue
                h, g = (c.windows(window, base)[at] for base in _BASES)
                g >>= np.uint64(32)  # 96 bits in all
                order = np.lexsort((ids[c.row[at]], g, h))
                h, g, at = h[order], g[order], at[order]
                starts, n = runs_of_pairs(h, g)
                first = np.repeat(ids[c.row[at[starts]]], n)
                later = ids[c.row[at]] > first
                out += _relay(_hit_rows(signed_ids(ids[c.row[at[later]]]), c.pos[at[later]], parts), buckets)
                least = ~later
                out += _send(h[least], g[least], c.row[at[least]], c.pos[at[least]], ids, buckets)
        return pa.Table.from_batches([_batch(out, _SENT_TYPE)] if out else [], _SENT_TYPE)

    return run


def runs_of_pairs(h: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    starts = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (g[1:] != g[:-1])]) if h.size else np.zeros(0, np.int64)
    return starts, np.diff(np.r_[starts, h.size])


def _match_windows(parts: int):
    def run(rows: pa.Table) -> pa.Table:
        h, g, ids, p, done = _entries(rows)
        out = done
        if h.size:
            order = np.lexsort((ids, g, h))
            h, g, ids, p = h[order], g[order], ids[order], p[order]
            starts, n = runs_of_pairs(h, g)
            later = ids > np.repeat(ids[starts], n)
            out = done + list(_hit_rows(signed_ids(ids[later]), p[later], parts))
        return pa.Table.from_batches([_batch(out, _HITS_TYPE)] if out else [], _HITS_TYPE)

    return run


def repeats(docs: DataFrame, window: int = 13, block: int = 7) -> tuple[DataFrame, int]:
    """Blobs (part, ids, n, p) of the places where a window starts that also starts in a
    document of smaller id, and the number of parts. docs: doc_id long, text."""
    if 2 * block - 1 > window:
        raise ValueError("a window must hold a whole reference block: 2 * block - 1 <= window")
    spark = docs.sparkSession
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(2 * shuffle_partitions(spark), -(-size // TASK_BYTES))
    parts = max(shuffle_partitions(spark), -(-size // TASK_BYTES)) | 1
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    hits = cut(rows.mapInArrow(_anchors(block, buckets, parts), _SENT).groupBy("key").applyInArrow(_match_anchors(parts), _HITS))
    at = rows.where("doc_id is not null").withColumn("part", id_bucket(F.col("doc_id"), parts))
    sent = at.groupBy("part").cogroup(hits.groupBy("part")).applyInArrow(_extend(block, window, buckets, parts), _SENT)
    return cut(sent.groupBy("key").applyInArrow(_match_windows(parts), _HITS)), parts


def _cut_words(texts: list[bytes], places: list[np.ndarray | None], window: int):
    for text, p in zip(texts, places, strict=True):
        words = text.split()
        n = len(words)
        if p is None or not n:
            yield n, 0, words, None
            continue
        p = p[p <= n - window]
        depth = np.zeros(n + 1, np.int64)
        np.add.at(depth, p, 1)
        np.add.at(depth, p + window, -1)
        keep = np.cumsum(depth[:n]) == 0
        yield n, int(n - keep.sum()), [w for w, k in zip(words, keep.tolist(), strict=True) if k], keep


def remove_repeats(docs: DataFrame, window: int = 13, block: int = 7, texts: bool = True, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_words, n_removed, kept_sha256, with
    ``texts`` kept_text (the kept words joined by one space; the text itself, null included,
    where nothing is removed), and the columns of ``carry`` as they are."""
    found, parts = repeats(docs, window, block)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *carry)
    names = ["doc_id", "n_words", "n_removed", "kept_sha256", *["kept_text"] * texts, *carry]
    if len(set(names)) < len(names):
        raise ValueError(f"a column that is carried has the name of a result: {names}")
    kinds = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), *[("kept_text", pa.string())] * texts])

    def run(own: pa.Table, hits: pa.Table) -> pa.Table:
        places, out = _hits_of(hits), []
        for b in text_slices(own.select(["doc_id", "text", *carry]).to_batches()):
            ids = b.column(0).to_pylist()
            cols: list[list] = [[], [], [], []]
            for (n, gone, kept, _), whole in zip(_cut_words(raw_texts_of(b), [places.get(i) for i in ids], window), b.column(1).to_pylist(), strict=True):
                joined = b" ".join(kept)
                cols[0].append(n)
                cols[1].append(gone)
                cols[2].append(hashlib.sha256(joined).hexdigest())
                cols[3].append(joined.decode("utf-8", "replace") if gone else whole)
            arrays = [pa.array(ids, pa.int64()), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.string()), pa.array(cols[3], pa.string())]
            out.append(pa.RecordBatch.from_arrays([*arrays[: 4 + texts], *b.columns[2:]], names))
        return pa.Table.from_batches(out) if out else pa.Table.from_batches([], pa.schema([*kinds, *(own.schema.field(c) for c in carry)]))

    # rows without an id go to any part: no hit is theirs
    part = F.coalesce(id_bucket(F.col("doc_id"), parts), F.pmod(F.xxhash64("text"), F.lit(parts)).cast("int"))
    given = dict(rows.dtypes)
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * texts + "".join(f", `{c}` {given[c]}" for c in carry)
    return rows.withColumn("_part", part).groupBy("_part").cogroup(found.withColumnRenamed("part", "_part").groupBy("_part")).applyInArrow(run, schema)
