"""Near-duplicate vectors: random-hyperplane sign hashing in several tables, exact cosine
in double precision within a bucket, links counted and joined to connected components.

Only rows of equal, non-null label are compared. Equal vectors of a label are one class
first, so a thousand copies are one row with a count. Buckets are compared twice: first by
a sketch of SKETCH sign bits, which is all that travels to every table, then those members
that have a plausible neighbour there are compared by their vectors. A bucket is dealt
into tiles and each pair of its tiles is one matrix product; small buckets share a task.
A pair of classes counts in the first table where it meets, so links are counted once
without being listed, and a task passes on only a spanning forest of what it linked.

Null, zero and ragged-null or non-finite vectors and rows without label link with nothing:
n_links 0, their own component. A null vec_id is kept as a row of its own that links with
nothing. Rows that repeat a vec_id are a vector each and share the id's component. Other
columns play no part, whatever their names.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, connected, cut, runs

#: Classes in a tile; a bucket of more is dealt into several.
TILE = 2048
#: Rows of small buckets that share a task.
LOT = 1 << 16
#: Sign bits of a sketch. Vectors at an angle a differ in SKETCH * a / pi bits in the mean.
SKETCH = 256
_BUCKET = ["label", "dim", "t", "key"]


def plan_tables(n: int, cosine: float, recall: float) -> tuple[int, int]:
    """Sign bits of a table, and tables, for n vectors of a label: about 32 random vectors
    meet in a bucket, and a pair at the threshold meets in some table with ``recall``."""
    bits = max(6, min(30, math.ceil(math.log2(max(n, 64) / 32))))
    meet = (1 - math.acos(cosine) / math.pi) ** bits
    return bits, math.ceil(math.log(1 - recall) / math.log(1 - meet))


def sketch_radius(cosine: float) -> int:
    """Differing sketch bits that vectors at the threshold have at most: six standard deviations."""
    p = math.acos(cosine) / math.pi
    return math.ceil(SKETCH * p + 6 * math.sqrt(SKETCH * p * (1 - p)))


def _planes(dim: int, count: int, seed: int) -> np.ndarray:
    return np.random.default_rng([seed, dim, count]).standard_normal((dim, count))


def _matrix(blobs: list[bytes]) -> np.ndarray:
    """Vectors of one dimension, each as a byte that tells its width, and its numbers."""
    out = np.empty((len(blobs), (len(blobs[0]) - 1) // blobs[0][0]))
    for width in {b[0] for b in blobs}:
        at = [k for k, b in enumerate(blobs) if b[0] == width]
        out[at] = np.frombuffer(b"".join([blobs[k][1:] for k in at]), f"<f{width}").reshape(len(at), -1)
    return out


def _signs(bits: int, tables: int, seed: int):
    """Adds to each class its dimension, its keys in all tables and its sketch."""

    def run(batches):
        for b in batches:
            blobs = b.column("v").to_pylist()
            dims = np.array([(len(v) - 1) // v[0] for v in blobs], np.int32)
            keys, sketches = np.zeros((len(blobs), tables), np.int32), [b""] * len(blobs)
            for dim in np.unique(dims).tolist():
                own = np.flatnonzero(dims == dim)
                x = _matrix([blobs[k] for k in own])
                keys[own] = (x @ _planes(dim, tables * bits, seed) >= 0).reshape(own.size, tables, bits) @ (1 << np.arange(bits))
                for k, row in zip(own.tolist(), np.packbits(x @ _planes(dim, SKETCH, seed + 1) >= 0, axis=1), strict=True):
                    sketches[k] = row.tobytes()
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(blobs) + 1, dtype=np.int32) * tables), pa.array(keys.reshape(-1)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(dims), lists, pa.array(sketches, pa.binary())], [*b.schema.names, "dim", "keys", "sketch"])

    return run


def _in_lots(rows: DataFrame, tile: int, lot: int):
    """Rows grouped for comparison: a bucket of more than ``tile`` rows by pairs of its tiles
    (side 0 or 1 by which of them a row is in, 2 if they are one), others many to a task."""
    big = rows.groupBy(*_BUCKET).agg(F.count(F.lit(1)).alias("m")).where(F.col("m") > tile).select(*_BUCKET, F.ceil(F.col("m") / tile).cast("int").alias("tiles"))
    lots = max(1, -(-rows.count() // lot))
    dealt = rows.join(big, _BUCKET, "left").withColumn("tiles", F.coalesce("tiles", F.lit(1)))
    dealt = dealt.withColumn("tile", F.pmod(F.xxhash64("rep", "vh"), F.col("tiles")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    bucket = F.xxhash64(*_BUCKET)
    dealt = dealt.withColumn("large", F.col("tiles") > 1).withColumn("lot", F.when(F.col("tiles") > 1, bucket).otherwise(F.pmod(bucket, F.lit(lots))))
    dealt = dealt.withColumn("low", F.least("tile", "other")).withColumn("high", F.greatest("tile", "other"))
    side = F.when(F.col("tile") == F.col("other"), 2).when(F.col("tile") == F.col("low"), 0).otherwise(1)
    return dealt.withColumn("side", side).drop("tiles", "tile", "other").groupBy("large", "lot", "low", "high")


def _buckets(rows: pa.Table):
    """Places of the rows of each bucket of a task: those of one side and of the other, the
    same array where a bucket is compared with itself."""
    each = [rows.column(c).to_numpy() for c in _BUCKET]
    side = rows.column("side").to_numpy()
    order = np.lexsort(each)
    new = np.zeros(order.size, bool)
    for c in each:
        new[1:] |= c[order[1:]] != c[order[:-1]]
    for start, n in zip(*runs(np.cumsum(new)), strict=True):
        at = order[start : start + n]
        if (side[at] == 2).any():
            yield at, at
        else:
            yield at[side[at] == 0], at[side[at] == 1]


def _plausible(radius: int):
    """Members (bucket, rep, vh) that have another one within the radius by sketch."""

    def run(rows: pa.Table) -> pa.Table:
        words = np.frombuffer(b"".join(rows.column("sketch").to_pylist()), "<u8").reshape(-1, SKETCH // 64)
        keep = np.zeros(len(words), bool)
        for a, b in _buckets(rows):
            for lo in range(0, a.size if b.size > 1 or a is not b else 0, 512):
                own = a[lo : lo + 512]
                near = sum(np.bitwise_count(words[own, k, None] ^ words[None, b, k]).astype(np.int16) for k in range(words.shape[1])) <= radius
                if a is b:
                    near[np.arange(own.size), lo + np.arange(own.size)] = False
                keep[own] |= near.any(1)
                keep[b] |= near.any(0)
        return rows.select([*_BUCKET, "rep", "vh"]).filter(pa.array(keep))

    return run


def _compare(cosine: float):
    """Rows (rep, vh, links, root) of the members that link."""

    def run(rows: pa.Table) -> pa.Table:
        rep, n, table = rows.column("rep").to_numpy(), rows.column("n").to_numpy(), rows.column("t").to_numpy()
        blobs = rows.column("v").to_pylist()
        keys = rows.column("keys").combine_chunks().flatten().to_numpy().reshape(len(rep), -1)
        links, root = np.zeros(len(rep), np.int64), rep.copy()
        for a, b in _buckets(rows):
            if not b.size or (a is b and b.size < 2):
                continue
            at = a if a is b else np.r_[a, b]
            x = _matrix([blobs[k] for k in at])
            norm, t, first = np.sqrt(np.einsum("ij,ij->i", x, x)), int(table[at[0]]), 0 if a is b else a.size
            label = np.arange(at.size)
            for lo in range(0, a.size, 512):
                own = np.arange(lo, min(lo + 512, a.size))
                i, j = np.nonzero((x[own] @ x[first:].T) >= cosine * np.outer(norm[own], norm[first:]))
                i, j = i + lo, j + first
                ok = i < j if a is b else np.ones(i.size, bool)
                if t:
                    ok[ok] = ~(keys[at[i[ok]], :t] == keys[at[j[ok]], :t]).any(1)
                i, j = i[ok], j[ok]
                links[at] += np.bincount(i, n[at[j]], at.size).astype(np.int64) + np.bincount(j, n[at[i]], at.size).astype(np.int64)
                label = connected(at.size, i, j, label)
            root[at] = rep[at][label]
        hit = np.flatnonzero(links)
        return pa.table({"rep": pa.array(rep[hit], pa.int64()), "vh": rows.column("vh").take(pa.array(hit)), "links": pa.array(links[hit], pa.int64()), "root": pa.array(root[hit], pa.int64())})

    return run


def _vector_bytes(batches):
    """Vectors that can link as bytes (see _matrix), null for the others."""
    for b in batches:
        out = []
        for v in b.column("embedding").to_pylist():
            ok = v and None not in v
            x = np.asarray(v, np.float64) if ok else None
            big = np.abs(x).max() if ok and np.isfinite(x).all() else 0.0
            if not big > 0:
                out.append(None)
                continue
            # a power of two brings any length near 1 without changing a cosine
            x = np.ldexp(x, -int(np.frexp(big)[1]))
            half = x.astype("<f4")
            out.append(b"\x04" + half.tobytes() if (half == x).all() else b"\x08" + x.astype("<f8").tobytes())
        yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("label"), pa.array(out, pa.binary())], ["vec_id", "label", "v"])


def near_vectors(vectors: DataFrame, cosine: float = 0.93, recall: float = 0.995, seed: int = 29) -> DataFrame:
    """vectors: vec_id long, embedding array, label. Returns vec_id, n_links, component_id
    and kept of each row. What is shuffled for every table is a key, an id and a sketch;
    vectors go only to the tables where a plausible neighbour waits."""
    own = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"), F.col("label").cast("long").alias("label"))
    rows = cut(own.mapInArrow(_vector_bytes, "vec_id long, label long, v binary"))
    usable = rows.where("v is not null and label is not null and vec_id is not null")
    # rep and vh name a class: two classes have one rep only where rows repeat a vec_id
    classes = cut(usable.groupBy("label", "v").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("n")).withColumn("vh", F.xxhash64("v")))
    most = classes.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    bits, tables = plan_tables(most, cosine, recall)
    signed = cut(classes.mapInArrow(_signs(bits, tables, seed), "label long, v binary, rep long, n long, vh long, dim int, keys array<int>, sketch binary"))
    keyed = signed.select("label", "dim", F.posexplode("keys").alias("t", "key"), "rep", "vh", "sketch")
    plausible = cut(_in_lots(keyed, TILE, LOT).applyInArrow(_plausible(sketch_radius(cosine)), "label long, dim int, t int, key int, rep long, vh long").distinct())
    full = cut(plausible.join(signed.select("rep", "vh", "n", "v", "keys"), ["rep", "vh"]))
    met = cut(_in_lots(full, TILE, LOT // 16).applyInArrow(_compare(cosine), "rep long, vh long, links long, root long"))
    parts = components(met.select(F.col("rep").alias("a"), F.col("root").alias("b")))
    links = met.groupBy("rep", "vh").agg(F.sum("links").alias("links"))
    found = cut(
        classes.join(links, ["rep", "vh"], "left").join(parts.withColumnRenamed("node", "rep"), "rep", "left")
        .select("label", "v", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("links"), F.coalesce("component", "rep").alias("component"))
    )
    out = rows.join(found, ["label", "v"], "left")
    component = F.when(F.col("component").isNotNull() & F.col("vec_id").isNotNull(), F.col("component")).otherwise(F.col("vec_id"))
    return out.select(
        "vec_id",
        F.when(F.col("vec_id").isNotNull(), F.coalesce("links", F.lit(0))).otherwise(F.lit(0)).cast("long").alias("n_links"),
        component.alias("component_id"),
        F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"),
    )
