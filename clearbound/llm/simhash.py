"""SimHash near-dedup by tiled exact comparison.

Every pair of fingerprints within the radius is found by exclusive-or and bit counts
over pairs of tiles. A tile holds fingerprints of one pair of half-word population
counts; two tiles whose counts differ by more than the radius in sum cannot hold a link
and are never paired. Equal fingerprints are one class first, and a tile pair passes on
a spanning forest of what it linked, so a large group costs its size, not its pairs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import components, connected, cut, gathered, raw_texts_of, runs, text_slices

SEED = 42
#: Fingerprints in a tile.
TILE = 8192


def shingle_hashes(text: bytes, width: int) -> np.ndarray:
    """XXH64 of the shingles of ``width`` words, A-Z lower-cased, repeats included."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, "<u8")
    joined = b" ".join(words)
    h = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([h(joined, SEED)], "<u8")
    gaps = np.flatnonzero(np.frombuffer(joined, np.uint8) == 32)
    starts = [0, *(gaps[: len(words) - width] + 1).tolist()]
    ends = [*gaps[width - 1 :].tolist(), len(joined)]
    return np.array([h(joined[s:e], SEED) for s, e in zip(starts, ends, strict=True)], "<u8")


#: Hashes whose bits are unpacked at once; sums of 255 rows of bits stay bytes.
_SLICE = 255 * 128


def majority(hashes: np.ndarray) -> bytes:
    """A bit for each bit of the rows of ``hashes`` (n x words of 64 bits), set in over half
    of them; without rows all bits are 0."""
    n = len(hashes)
    if not n:
        return bytes(8 * hashes.shape[1])
    ones = np.zeros(64 * hashes.shape[1], np.int64)
    for at in range(0, n, _SLICE):
        bits = np.unpackbits(np.ascontiguousarray(hashes[at : at + _SLICE]).view(np.uint8), axis=1, bitorder="little")
        ones += np.add.reduceat(bits, np.arange(0, len(bits), 255), axis=0, dtype=np.uint8).sum(0, dtype=np.int64)
    return np.packbits(2 * ones > n, bitorder="little").tobytes()


def majority_bits(hashes: np.ndarray) -> int:
    """Bits set in over half of the hashes; none: 0."""
    return int.from_bytes(majority(hashes.reshape(-1, 1)), "little")


def fingerprint(text: bytes, width: int) -> int:
    return majority_bits(shingle_hashes(text, width))


def fingerprints(docs: DataFrame, width: int = 4) -> DataFrame:
    """doc_id and fp (the 64 bits as a signed long) of each row; null and empty texts: 0."""

    def run(batches):
        for b in text_slices(batches):
            fp = np.array([fingerprint(t, width) for t in raw_texts_of(b)], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], ["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, fp long")


def _counts(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.bitwise_count(fp & np.uint64(0xFFFFFFFF)).astype(np.int64), np.bitwise_count(fp >> np.uint64(32)).astype(np.int64)


def _tiles(parts: dict[tuple[int, int], int], radius: int):
    """A row for each pair of tiles that a fingerprint's own tile takes part in."""
    cells = [(a, b) for a in range(-radius, radius + 1) for b in range(-radius, radius + 1) if abs(a) + abs(b) <= radius]

    def run(batches):
        for b in gathered(batches, 1 << 20):
            fp = b.column("fp").to_numpy().view(np.uint64)
            low, high = _counts(fp)
            mix = (fp * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)
            keys = low * 64 + high
            for key in np.unique(keys).tolist():
                p, q = divmod(key, 64)
                own = np.flatnonzero(keys == key)
                sub = (mix[own] % np.uint64(parts[p, q])).astype(np.int64)
                for s in np.unique(sub).tolist():
                    block = pa.array(fp[own[sub == s]].view(np.int64))
                    mine = key << 32 | s
                    names, sides = [], []
                    for dp, dq in cells:
                        for t in range(parts.get((p + dp, q + dq), 0)):
                            other = ((p + dp) * 64 + q + dq) << 32 | t
                            names.append((min(mine, other), max(mine, other)))
                            sides.append(2 if mine == other else int(mine > other))
                    n = len(block)
                    for name, side in zip(names, sides, strict=True):
                        yield pa.RecordBatch.from_arrays([pa.array([name[0]]), pa.array([name[1]]), pa.array([side], pa.int32()), pa.array([np.asarray(block).tobytes()], pa.binary())], ["low", "high", "side", "block"]) if n else None

    return lambda batches: (x for x in run(batches) if x is not None)


def _compare(radius: int):
    def run(rows: pa.Table) -> pa.Table:
        side, blocks = rows.column("side").to_pylist(), rows.column("block").to_pylist()
        take = lambda k: np.frombuffer(b"".join(x for s, x in zip(side, blocks, strict=True) if s == k), "<u8")
        a, b = take(0), take(1)
        one = 2 in side
        if one:
            a = b = take(2)
        every = np.unique(np.concatenate([a, b]))
        at_a, at_b, label = np.searchsorted(every, a), np.searchsorted(every, b), np.arange(every.size)
        step = max(1, (1 << 18) // max(1, b.size))
        for lo in range(0, a.size, step):
            i, j = np.nonzero(np.bitwise_count(a[lo : lo + step, None] ^ b[None, :]) <= radius)
            label = connected(every.size, at_a[i + lo], at_b[j], label)
        at = np.flatnonzero(label != np.arange(every.size))
        return pa.table({"a": pa.array(every[at].view(np.int64), pa.int64()), "b": pa.array(every[label[at]].view(np.int64), pa.int64())})

    return run


def link_fingerprints(classes: DataFrame, radius: int = 4, tile: int = TILE) -> DataFrame:
    """(a, b): a spanning forest of the links among the distinct ``fp`` of ``classes``.
    The histogram that the tiles are made from has at most 33 * 33 rows."""

    def cells(batches):
        for b in batches:
            low, high = _counts(b.column("fp").to_numpy().view(np.uint64))
            keys, n = np.unique(low * 64 + high, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(n)], ["cell", "n"])

    sizes = classes.select("fp").mapInArrow(cells, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).collect()
    parts = {divmod(r["cell"], 64): -(-r["n"] // tile) for r in sizes}
    dealt = classes.select("fp").mapInArrow(_tiles(parts, radius), "low long, high long, side int, block binary")
    return dealt.groupBy("low", "high").applyInArrow(_compare(radius), "a long, b long")


def near_documents(docs: DataFrame, width: int = 4, radius: int = 4) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id that links reach)
    of each row. A null doc_id takes part in linking and names no component unless all of
    its component's ids are null."""
    rows = cut(fingerprints(docs, width))
    classes = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("least")))
    found = components(cut(link_fingerprints(classes, radius)))
    named = classes.join(found.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    # cut, so that the join's two sides are exchanges and a component of very many rows is split
    low = cut(named.groupBy("component").agg(F.min("least").alias("component_id")))
    names = named.join(low, "component").select("fp", "component_id")
    return rows.join(names, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


# -- groups by similarity: SimHash sketches find candidates, shingle sets decide

#: Minima of a signature.
SLOTS = 256
#: Bits of a sketch: a SimHash of a set of shingles, of two 64-bit hashes of each.
BITS = 128
#: At a similarity of .8 two sketches of many shingles differ in 19.3 bits in the mean, sd 4.0; those of four and of
#: five shingles in 24, sd 4.4, the most of all: seven standard deviations. Random ones in 64, sd 5.7.
RADIUS = 56
#: Signatures (sd .025 at .8) pass this far under the similarity: six standard deviations.
MARGIN = 0.15
#: Bands of a signature and minima of each: 1 - (1 - .8^5)^51 at a similarity of .8.
BANDS, ROWS = 51, 5
_FACTORS = np.random.default_rng(17).integers(1, 1 << 32, SLOTS, dtype=np.uint32) | np.uint32(1)
#: Pairs whose signatures are held side by side at once.
_AT_ONCE = 1 << 15


def minima(hashes: np.ndarray) -> np.ndarray:
    """The minimum of each of SLOTS orders of the shingles; none: zeros."""
    if not len(hashes):
        return np.zeros(SLOTS, np.uint32)
    h = np.unique((hashes >> np.uint64(32)).astype(np.uint32))
    least = np.full(SLOTS, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(h), 512):
        least = np.minimum(least, (h[at : at + 512, None] * _FACTORS[None, :]).min(0))
    return least


def signature(least: np.ndarray) -> bytes:
    """A byte of each of the minima."""
    return (least & np.uint32(0xFF)).astype(np.uint8).tobytes()


def sketch(shingles: np.ndarray) -> bytes:
    """BITS majority bits of a set of shingle hashes, so that repeats of a line change nothing."""
    more = (shingles ^ (shingles >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return majority(np.stack([shingles, (more ^ (more >> np.uint64(32))) * np.uint64(0x94D049BB133111EB)], axis=1))


def _signed(width: int):
    def run(batches):
        for b in text_slices(batches):
            same, sketches, sigs = [], [], []
            for t in raw_texts_of(b):
                own = np.unique(shingle_hashes(t, width))
                same.append(set_hash(own))
                sketches.append(sketch(own))
                sigs.append(signature(minima(own)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(same, pa.int64()), pa.array(sketches, pa.binary()), pa.array(sigs, pa.binary())], ["doc_id", "text_hash", "same", "sketch", "sig"])

    return run


def set_hash(shingles: np.ndarray) -> int:
    """64 bits that name a set of shingles, given in order."""
    return int(np.uint64(xxhash.xxh64_intdigest(shingles.tobytes(), SEED)).view(np.int64))


def _banded(batches):
    """(band, key): a 64-bit hash of each of BANDS runs of ROWS bytes of a signature and its
    number."""
    h = xxhash.xxh64_intdigest
    for b in gathered(batches, 1 << 14):
        sigs = b.column("sig").to_pylist()
        bands = np.array([h(x[k * ROWS : (k + 1) * ROWS], k) for x in sigs for k in range(BANDS)], np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(bands), pa.array(np.repeat(b.column("key").to_numpy(), BANDS))], ["band", "key"])


def _pairs_within(n: np.ndarray):
    """Pairs of places of runs of n[0], n[1], ... rows, each with itself, some at a time."""
    starts = np.cumsum(n) - n
    ends = np.repeat(starts + n, n)
    later = ends - np.arange(ends.size) - 1  # rows of its run behind each row
    at = np.cumsum(later)
    lo = 0
    while lo < later.size:
        hi = max(lo + 1, int(np.searchsorted(at, (at[lo - 1] if lo else 0) + 8 * _AT_ONCE, side="right")))
        m = later[lo:hi]
        i = np.repeat(np.arange(lo, hi), m)
        if i.size:
            yield i, np.arange(i.size) - np.repeat(np.cumsum(m) - m, m) + i + 1
        lo = hi


def _verified(radius: int, similarity: float):
    """Spanning forest (a, b) of the links of a task's buckets: sketches within the radius and
    signatures similar enough. Pairs that are connected already are not compared again."""
    least = similarity + (1 - similarity) / 256  # bytes agree by chance

    def run(rows: pa.Table) -> pa.Table:
        order = np.argsort(rows.column("band").to_numpy(), kind="stable")
        band, key, side = (rows.column(c).to_numpy()[order] for c in ("band", "key", "side"))
        words = np.frombuffer(b"".join(rows.column("sketch").to_pylist()), "<u8").reshape(-1, BITS // 64)[order]
        sigs = np.frombuffer(b"".join(rows.column("sig").to_pylist()), np.uint8).reshape(-1, SLOTS)[order]
        names, at = np.unique(key, return_inverse=True)
        root = np.arange(names.size)
        if (side == 2).all():
            pairs = _pairs_within(runs(band)[1])
        else:  # two tiles of one bucket
            a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            step = max(1, 8 * _AT_ONCE // max(1, b.size))
            pairs = ((np.repeat(a[k : k + step], b.size), np.tile(b, a[k : k + step].size)) for k in range(0, a.size, step))
        for i, j in pairs:
            apart = root[at[i]] != root[at[j]]
            i, j = i[apart], j[apart]
            near = np.bitwise_count(words[i] ^ words[j]).sum(1, dtype=np.int64) <= radius
            i, j = i[near], j[near]
            for lo in range(0, i.size, _AT_ONCE):
                p, q = i[lo : lo + _AT_ONCE], j[lo : lo + _AT_ONCE]
                ok = (sigs[p] == sigs[q]).sum(1) >= least * SLOTS
                if ok.any():
                    root = connected(names.size, at[p[ok]], at[q[ok]], root)
        moved = np.flatnonzero(root != np.arange(names.size))
        return pa.table({"a": pa.array(names[moved], pa.int64()), "b": pa.array(names[root[moved]], pa.int64())})

    return run


def _in_buckets(classes: DataFrame, tile: int, lot: int):
    """Classes (key, sketch, sig) grouped for comparison with those that share a band: many
    small buckets to a task, one of more than ``tile`` rows by pairs of its tiles. A band and
    a key are sent for every class, sketch and signature only where a bucket has two."""
    bands = classes.select("key", "sig").mapInArrow(_banded, "band long, key long")
    met = cut(bands.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("band"))).where("n > 1"))
    lots = max(1, -(-met.count() // lot))
    split = met.withColumn("tiles", F.ceil(F.col("n") / tile).cast("int")).withColumn("tile", F.pmod(F.xxhash64("key"), F.col("tiles")).cast("int"))
    split = split.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    large = F.col("tiles") > 1
    side = F.when(F.col("tile") == F.col("other"), 2).when(F.col("tile") < F.col("other"), 0).otherwise(1)
    dealt = split.select("band", "key", large.alias("large"), F.when(large, F.col("band")).otherwise(F.pmod("band", F.lit(lots))).alias("lot"), F.least("tile", "other").alias("low"), F.greatest("tile", "other").alias("high"), side.alias("side"))
    return dealt.join(classes.select("key", "sketch", "sig"), "key").groupBy("large", "lot", "low", "high")


def _sets(width: int):
    """The shingle sets of the rows whose set is the one that ``node`` names."""

    def run(batches):
        for b in text_slices(batches):
            sets = [np.unique(shingle_hashes(t, width)) for t in raw_texts_of(b)]
            own = np.array([set_hash(x) for x in sets], np.int64) == b.column("node").to_numpy()
            part = b.filter(pa.array(own))
            kept = [x for x, k in zip(sets, own, strict=True) if k]
            yield pa.RecordBatch.from_arrays([part.column("component"), part.column("node"), pa.array([len(x) for x in kept], pa.int64()), pa.array([x.tobytes() for x in kept], pa.binary())], ["component", "node", "n", "shingles"])

    return run


def _alike(sets: list[np.ndarray], block: np.ndarray, similarity: float) -> np.ndarray:
    """For each set the first one that links of the similarity reach; with two blocks only
    pairs across them are compared, and pairs that are connected already never."""
    sizes, label = np.array([len(x) for x in sets]), np.arange(len(sets))
    terms = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts = np.cumsum(sizes) - sizes
    held, two = np.zeros(terms.max(initial=-1) + 1, np.uint8), block.min() != block.max()
    for i in range(len(sets) - 1):
        j = np.arange(i + 1, len(sets))
        asked = (label[j] != label[i]) & (np.minimum(sizes[j], sizes[i]) >= similarity * np.maximum(sizes[j], sizes[i]) - 1e-9)
        j = j[asked & (block[j] != block[i])] if two else j[asked]
        if not j.size:
            continue
        own, n = terms[starts[i] : starts[i] + sizes[i]], sizes[j]
        before = np.cumsum(n) - n
        held[own] = 1
        both = np.add.reduceat(held[terms[np.arange(n.sum()) + np.repeat(starts[j] - before, n)]], before, dtype=np.int64)
        held[own] = 0
        hit = j[both >= similarity * (sizes[i] + n - both) - 1e-9]
        if hit.size:
            joined = np.unique(np.r_[label[i], label[hit]])
            label[np.isin(label, joined)] = joined[0]
    return label


def _linked(similarity: float):
    """Spanning forest (a, b) of the exact links within each coarse group of a task."""

    def run(rows: pa.Table) -> pa.Table:
        group, node, block = (rows.column(c).to_numpy() for c in ("component", "node", "block"))
        blobs, a, b = rows.column("shingles").to_pylist(), [], []
        order = np.argsort(group, kind="stable")
        for start, n in zip(*runs(group[order]), strict=True):
            at = order[start : start + n]
            at = at[np.unique(node[at], return_index=True)[1]]
            label = _alike([np.frombuffer(blobs[k], "<u8") for k in at], block[at], similarity)
            moved = np.flatnonzero(label != np.arange(at.size))
            a.append(node[at[moved]])
            b.append(node[at[label[moved]]])
        return pa.table({"a": pa.array(np.concatenate(a), pa.int64()), "b": pa.array(np.concatenate(b), pa.int64())})

    return run


def _exact_links(docs: DataFrame, coarse: DataFrame, width: int, similarity: float, most_shingles: int, most_sets: int) -> DataFrame:
    """(a, b): links among the nodes of ``coarse`` (node, component, key, text_hash) by the
    similarity of their shingle sets. A set goes once to the task of its group; a group beyond
    the bounds is split into blocks that are compared by pairs. A node without key is read
    from the rows without doc_id, each text of them once."""
    picked = docs.select("doc_id", "text").join(coarse.where("key is not null").select("component", "node", F.col("key").alias("doc_id")), "doc_id").select("component", "node", "text")
    alone = docs.where("doc_id is null").select("text").distinct().withColumn("text_hash", F.xxhash64("text"))
    picked = picked.unionByName(alone.join(coarse.where("key is null"), "text_hash").select("component", "node", "text"))
    sets = cut(picked.mapInArrow(_sets(width), "component long, node long, n long, shingles binary"))
    sizes = sets.groupBy("component").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("m"))
    sizes = cut(sizes.select("component", "n", F.greatest(F.ceil(F.col("n") / most_shingles), F.ceil(F.col("m") / most_sets), F.lit(1)).cast("int").alias("blocks")))
    tasks = max(1, -(-(sizes.agg(F.sum("n")).first()[0] or 0) // most_shingles))
    split = sets.join(F.broadcast(sizes.where("blocks > 1").drop("n")), "component", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    split = split.withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = split.select("component", "node", "block", "shingles", (F.col("blocks") > 1).alias("big"), F.when(F.col("blocks") > 1, F.col("component")).otherwise(F.pmod(F.xxhash64("component"), F.lit(tasks))).alias("task"), F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"))
    return dealt.groupBy("big", "task", "low", "high").applyInArrow(_linked(similarity), "a long, b long")


def similar_documents(docs: DataFrame, width: int = 5, similarity: float = 0.8, tile: int = 4 * TILE, most_shingles: int = 1 << 21, most_sets: int = 8192) -> DataFrame:
    """doc_id, text_hash (xxhash64 of the text: tells rows that repeat a doc_id apart), group_id
    (any numbers) and component_id (smallest doc_id of the group) of each row. Linked are texts
    whose sets of shingles have the similarity, which is decided by the sets themselves
    (64-bit hashes of their shingles). Candidates share one of BANDS bands of their signatures,
    which about two in 10^9 pairs of similarity .8 do not, and have SimHash sketches within
    RADIUS bits and signatures that come within MARGIN of it, which fewer miss at any number of
    shingles; the groups that this makes are compared exactly. A row without doc_id is linked
    like any other and has a group; it names no component and has none (null). Texts without
    words are alike."""
    signed = docs.select("doc_id", "text", F.xxhash64("text").alias("text_hash")).mapInArrow(_signed(width), f"doc_id {dict(docs.dtypes)['doc_id']}, text_hash long, same long, sketch binary, sig binary")
    rows = cut(signed)
    classes = rows.groupBy("sketch", "same").agg(F.min("doc_id").alias("key"))
    asked = cut(rows.groupBy("sketch", "same").agg(F.min("doc_id").alias("id"), F.min("text_hash").alias("text_hash"), F.first("sig").alias("sig")).withColumnRenamed("same", "key"))
    links = _in_buckets(asked, tile, 1 << 16).applyInArrow(_verified(RADIUS, similarity - MARGIN), "a long, b long")
    coarse = components(cut(links)).join(asked.select(F.col("key").alias("node"), F.col("id").alias("key"), "text_hash"), "node")
    found = components(cut(_exact_links(docs, coarse, width, similarity, most_shingles, most_sets)))
    named = cut(classes.join(found.withColumnRenamed("node", "same"), "same", "left").withColumn("group", F.coalesce("component", "same")))
    least = cut(named.groupBy("group").agg(F.min("key").alias("component_id")))
    out = rows.select("doc_id", "text_hash", "sketch", "same").join(named.join(least, "group").select("sketch", "same", F.col("group").alias("group_id"), "component_id"), ["sketch", "same"])
    return out.select("doc_id", "text_hash", "group_id", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))
