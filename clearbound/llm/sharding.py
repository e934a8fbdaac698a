"""Sharding by a hierarchical weighted hash tree, in DataFrame functions alone.

Shards stand in racks and racks in regions. A shard draws an exponential variable from a
hash of the row's key and the shard's name, divided by the shard's weight, and the draw of
a rack or region is the least below it: an exponential again, whose rate is the weight of
all its shards. The row descends to the region, the rack and the shard of the least draw.
A change of one weight changes the draws on that shard's path to the root and no others,
so rows move into or out of that shard only, at every number of shards, filled racks and
regions or not. Null keys are hashed as such.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, number_within

RACKS_IN_REGION = 2
SHARDS_IN_RACK = 4
_SEED = 0x7EE5


def _once(value: Column, then) -> Column:
    """``then`` of a value computed once (a plain reference would be computed at each use)."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def _draws(key: Column, weights: list[float]) -> Column:
    """(draw, shard) of every shard; one without weight never wins."""
    each = F.array(*map(F.lit, weights))

    def drawn(i: Column) -> Column:
        unit = (F.pmod(F.xxhash64(key, F.lit(_SEED), i.cast("long")), F.lit(1 << 52)) + 0.5) / float(1 << 52)
        weight = F.get(each, i)
        return F.struct(F.when(weight > 0, -F.log(unit) / weight).otherwise(F.lit(float("inf"))).alias("draw"), i.alias("shard"))

    return F.transform(F.sequence(F.lit(0), F.lit(len(weights) - 1)), drawn)


def _above(draws: Column, n: int, span: int) -> tuple[Column, int]:
    """Draws of the nodes that hold ``span`` of n nodes each: the least of theirs."""
    nodes = -(-n // span)
    return F.transform(F.sequence(F.lit(0), F.lit(nodes - 1)), lambda i: F.array_min(F.slice(draws, i * span + 1, span))), nodes


def _winner(shards: Column, n: int) -> Column:
    """(draw, shard) that the tree over the first n shards leads to."""
    racks, m = _above(F.slice(shards, 1, n), n, SHARDS_IN_RACK)
    return _once(racks, lambda r: F.array_min(_above(r, m, RACKS_IN_REGION)[0]))


def shard_of(key: Column, shards: int, weights: list[float] | None = None) -> Column:
    """Shard of ``key`` in a tree of ``shards`` shards (of equal weight unless given)."""
    return _once(_draws(key, weights or [1.0] * shards), lambda d: _winner(d, shards))["shard"].cast("int")


def shard_documents(docs: DataFrame, shards: int = 40) -> DataFrame:
    """doc_id, size (UTF-8 bytes of the text and 16), text_crc32, law 'key', shard, slot
    (0, 1, 2, ... in its shard) and grown_shard (with one more shard). Rows that repeat a
    doc_id go to one shard and have slots of their own; null texts have no bytes. The texts
    are read once: what is numbered is a checkpoint of the other columns."""
    raw = F.coalesce(F.col("text").cast("binary"), F.lit(b""))
    # one more shard takes the rows whose draw for it is under their least
    both = _once(_draws(F.col("doc_id"), [1.0] * (shards + 1)), lambda d: _once(_winner(d, shards), lambda w: F.struct(w["shard"].alias("now"), F.least(w, F.get(d, F.lit(shards)))["shard"].alias("grown"))))
    rows = docs.select("doc_id", (F.octet_length(raw) + F.lit(16)).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"), both.alias("to"))
    rows = cut(rows.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), F.col("to.now").cast("int").alias("shard"), F.col("to.grown").cast("int").alias("grown_shard")))
    return number_within(rows, "shard", ["doc_id", "size", "text_crc32"], "slot").select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")
