"""Pieces shared by the operators: durable cuts, bounded text slices, compact
columns for exchanges, held-out folds and connected components."""

from __future__ import annotations

import ctypes
import os
import struct
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import spread

#: Text bytes that one vectorised step handles at once; bounds a worker's memory.
SLICE_BYTES = 1 << 20
#: Links up to which one task finds the components.
FEW_LINKS = 1 << 18


#: Rows of an Arrow batch at most: with the default of 10,000 a batch of long texts is
#: hundreds of megabytes on both sides of the pipe.
BATCH_ROWS = 1000
_BATCH_SETTING = "spark.sql.execution.arrow.maxRecordsPerBatch"


def bounded_batches(spark: SparkSession) -> None:
    """Holds Arrow batches to BATCH_ROWS rows. Plans read this runtime setting when they
    run, long after the call that made them, so it stays lowered for the session; a value
    of the caller's that is lower already is left alone."""
    now = int(spark.conf.get(_BATCH_SETTING))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(_BATCH_SETTING, str(BATCH_ROWS))


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share, as spark.checkpoint.dir names it. Without the
    setting only a session of one machine has a folder; on a cluster it is an error."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    return os.path.join(tempfile.gettempdir(), f"checkpoints-{os.getuid()}")


def remove_folder(spark: SparkSession, path: str) -> None:
    """Deletes a folder of intermediate data in whatever store it is in."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; a small one is dealt out over all cores."""
    bounded_batches(spark)
    return spread(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def shuffle_partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: Has Spark remove the shuffle files of a query when it ends.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame) -> DataFrame:
    """Run the plan once and cut its lineage with a reliable checkpoint in the shared
    folder. The shuffles of the finished part are removed with it: what they hold is in the
    checkpoint, and a stage that follows would else find the disk full of them."""
    spark = df.sparkSession
    bounded_batches(spark)
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(shared_folder(spark))
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        return df.select("*").checkpoint(eager=True)  # the setting holds for frames that are made under it
    finally:
        spark.conf.set(_CLEANUP, before)


def fold(doc_id: str | Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; null ids fall in fold 0."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.pmod(F.crc32(c.cast("string").cast("binary")), F.lit(n)), F.lit(0)).cast("int")


def _below(rows: int, n: int) -> int:
    """The hash under which ``rows`` of ``n`` rows lie: 64 bits, so that a share of one row in
    10^12 is still a share."""
    return min((1 << 63) - 1, (rows << 64) // max(n, 1) - (1 << 63))


def bounded_sample(df: DataFrame, key: str, rows: int, by: str | None = None) -> DataFrame:
    """About ``rows`` rows, or about ``rows`` of each value of ``by`` (a column of few values,
    one count of each comes to the driver), chosen by a hash of ``key``: the share is set
    from the count. All rows of a value that has no more."""
    drawn = F.xxhash64(F.col(key), F.lit(0x5EED))
    if by is None:
        n = df.count()
        return df if n <= rows else df.where(drawn < F.lit(_below(rows, n)))
    sizes = {r[by]: r["count"] for r in df.groupBy(by).count().collect()}
    keep = F.lit(True)
    for value, n in sizes.items():
        if n > rows:
            keep = F.when(F.col(by).eqNullSafe(F.lit(value)), drawn < F.lit(_below(rows, n))).otherwise(keep)
    return df.where(keep)


def text_slices(batches: Iterable[pa.RecordBatch], column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``limit`` text bytes (one long text stays whole)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(column))), 0).to_numpy(zero_copy_only=False))
        at = 0
        while at < batch.num_rows:
            base = ends[at - 1] if at else 0
            stop = max(at + 1, int(np.searchsorted(ends, base + limit, side="right")))
            yield batch.slice(at, stop - at)
            at = stop
    release()


def release() -> None:
    """Gives freed memory back at the end of a task: Spark uses a worker again and again, and
    it would else hold the most that any of its tasks has needed."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def gathered(batches: Iterable[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``rows`` rows, for rows of bounded size."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        held.append(b)
        if sum(x.num_rows for x in held) >= rows:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held = []
    if sum(x.num_rows for x in held):
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
    release()


def texts_of(batch: pa.RecordBatch, column: str = "text") -> list[str]:
    return ["" if x is None else x for x in batch.column(batch.schema.get_field_index(column)).to_pylist()]


def raw_texts_of(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    return [x or b"" for x in batch.column(batch.schema.get_field_index(column)).cast(pa.binary()).to_pylist()]


def pack(values: np.ndarray) -> bytes:
    """Unsigned numbers as byte planes without the planes that are zero throughout."""
    v = np.ascontiguousarray(values, dtype="<u8")
    k = (int(v.max()).bit_length() + 7) // 8 if v.size else 0
    return struct.pack("<IB", v.size, k) + v.view(np.uint8).reshape(-1, 8)[:, :k].T.tobytes()


def unpack(blob: bytes) -> np.ndarray:
    n, k = struct.unpack_from("<IB", blob)
    out = np.zeros((n, 8), np.uint8)
    if n and k:
        out[:, :k] = np.frombuffer(blob, np.uint8, n * k, 5).reshape(k, n).T
    return out.view("<u8").reshape(-1)


def pack_sorted(values: np.ndarray) -> bytes:
    """Ascending unsigned numbers as packed differences."""
    return pack(np.diff(values, prepend=values.dtype.type(0)))


def unpack_sorted(blob: bytes) -> np.ndarray:
    return np.cumsum(unpack(blob), dtype=np.uint64)


def ordered_bits(ids: np.ndarray) -> np.ndarray:
    """Signed ids as unsigned numbers of the same order."""
    return ids.astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)


def signed_ids(bits: np.ndarray) -> np.ndarray:
    return (bits ^ np.uint64(1 << 63)).view(np.int64)


def id_bucket(col: Column, n: int) -> Column:
    """A bucket of an id by bit mixing that numpy repeats exactly (see id_bucket_np)."""
    mixed = col.bitwiseXOR(F.shiftright(col, 17)).bitwiseXOR(F.shiftright(col, 31))
    return F.pmod(mixed, F.lit(n)).cast("int")


def id_bucket_np(ids: np.ndarray, n: int) -> np.ndarray:
    ids = ids.astype(np.int64)
    return (ids ^ (ids >> 17) ^ (ids >> 31)) % n


def runs(sorted_keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start of each run of equal keys, and its length."""
    if not sorted_keys.size:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    starts = np.flatnonzero(np.r_[True, sorted_keys[1:] != sorted_keys[:-1]])
    return starts, np.diff(np.r_[starts, sorted_keys.size])


def number_within(df: DataFrame, group: str, order: list[str], name: str, rows_per_part: int = 8192) -> DataFrame:
    """``name``: 0, 1, 2, ... within each value of ``group`` (of which there are few: their
    counts are joined by broadcast). A group is split by a hash of ``order`` into parts of
    about ``rows_per_part`` rows, the parts are counted, and a part's rows are numbered
    after those of the parts before it, so no task holds a whole group. The counts are one
    row for each part. Built of DataFrame functions; ``df`` is read three times, so it
    should be cut. Columns of it that begin with _number are not kept."""
    parts = df.groupBy(group).agg(F.ceil(F.count(F.lit(1)) / rows_per_part).alias("_number_parts"))
    split = df.join(F.broadcast(parts), group).withColumn("_number_part", F.pmod(F.xxhash64(*order), F.col("_number_parts")).cast("int"))
    sizes = split.groupBy(group, "_number_part").agg(F.count(F.lit(1)).alias("_number_n"))
    before = Window.partitionBy(group).orderBy("_number_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.withColumn("_number_base", F.coalesce(F.sum("_number_n").over(before), F.lit(0))).drop("_number_n")
    within = Window.partitionBy(group, "_number_part").orderBy(*order)
    return (
        split.withColumn("_number_row", F.row_number().over(within))
        .join(starts, [group, "_number_part"])
        .withColumn(name, (F.col("_number_base") + F.col("_number_row") - 1).cast("long"))
        .drop("_number_parts", "_number_part", "_number_base", "_number_row")
    )


def connected(n: int, a: np.ndarray, b: np.ndarray, label: np.ndarray | None = None) -> np.ndarray:
    """For each of n items the smallest item that links (a, b) reach, from the labels of an
    earlier call on. Minima are passed along all links at once until nothing changes."""
    label = np.arange(n) if label is None else label
    while a.size:
        apart = label[a] != label[b]
        if not apart.all():
            a, b = a[apart], b[apart]
        low = np.minimum(label[a], label[b])
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while (label[label] != label).any():
            label = label[label]
    return label


def _contracted(batches):
    """(node, component) of all links of a task."""
    held = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
    if held:
        a, b = (np.concatenate(x) for x in zip(*held, strict=True))
        nodes, at = np.unique(np.r_[a, b], return_inverse=True)
        label = connected(nodes.size, at[: a.size], at[a.size :])
        yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[label])], ["node", "component"])


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Connected components of ``links`` (a, b): one row (node, component) for each node
    that occurs, component being the smallest node reached. Up to FEW_LINKS links (4 MB) are
    one task's, which spares the rounds' many small stages. More: rounds of star contraction,
    each with map-side combined minima and a checkpoint, until the edges form stars. A
    node of very many edges is one key of the joins, which Spark splits as a skewed join:
    both sides of each join come out of a checkpoint or an exchange of their own."""
    edges = cut(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    if set(dict(edges.dtypes).values()) == {"bigint"} and edges.count() <= FEW_LINKS:
        return cut(edges.coalesce(1).mapInArrow(_contracted, "node long, component long"))
    seen = None
    for _ in range(most_rounds):
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = cut(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a")
        edges = cut(
            small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
            .unionByName(least.select("a", F.col("m").alias("b")))
            .distinct()
        )
        now = tuple(edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b"))).first())
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("connected components did not settle")
    roots = edges.select("b").distinct()
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(
        roots.select(F.col("b").alias("node"), F.col("b").alias("component"))
    )
