"""Recurring audit: micro-batches of new train records against a fixed eval side."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import lexical


def lexical_stream(records: DataFrame, evals: DataFrame, k: int = 5) -> DataFrame:
    """Stream-static join: the eval records that each new record (id, text) shares a k-gram
    with, and how many grams; stateless, so it runs in append mode."""
    e = lexical.gram_sets(evals, k).select(F.col("id").alias("e_id"), F.col("n").alias("e_n"), F.explode("grams").alias("gram"))
    t = lexical.gram_sets(records, k).select(F.col("id").alias("t_id"), F.explode("grams").alias("gram"))
    return t.join(F.broadcast(e), "gram").select("t_id", "e_id", "e_n", "gram")


def audit_batches(records: DataFrame, evals: DataFrame, ledger: str, checkpoint: str, tau: float = 0.4, once: bool = True):
    """foreachBatch: each micro-batch is audited as a batch and its flagged pairs are written
    under the batch number, so a batch that is delivered again overwrites itself."""

    def run(batch: DataFrame, number: int) -> None:
        lexical.pairs(batch.select("id", "text"), evals, tau=tau).withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{ledger}/batch={number}")

    writer = records.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()
