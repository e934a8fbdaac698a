"""Readers with fixed schemas, and sinks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Schemas of the tables that the methods read; a reader never infers them.
SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}

RECORD_SCHEMA = T.StructType([
    T.StructField("rec_id", T.LongType()), T.StructField("source", T.StringType()), T.StructField("text", T.StringType()), T.StructField("language", T.StringType()),
    T.StructField("licence", T.StringType()), T.StructField("messages", T.ArrayType(T.StructType([T.StructField("role", T.StringType()), T.StructField("content", T.StringType())]))),
    T.StructField("native_difficulty", T.StructType([T.StructField("scale", T.StringType()), T.StructField("value", T.IntegerType())])),
])


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reader = spark.read
    if name in SCHEMAS:
        reader = reader.schema(SCHEMAS[name])
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def read_jsonl(spark: SparkSession, path: str, schema=RECORD_SCHEMA) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: str, header: bool = True) -> DataFrame:
    return spark.read.schema(schema).option("header", header).csv(path)


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def write_parquet(df: DataFrame, path: str, by: list[str] | None = None, mode: str = "errorifexists") -> None:
    w = df.write.mode(mode)
    (w.partitionBy(*by) if by else w).parquet(path)


def write_jsonl(df: DataFrame, path: str, mode: str = "errorifexists") -> None:
    df.write.mode(mode).json(path)


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    """Doubles to six digits: what is published and compared. A sum's order is not fixed."""
    return df.select(*(F.round(F.col(f"`{c}`"), digits).alias(c) if t in ("double", "float") else F.col(f"`{c}`") for c, t in df.dtypes))


#: Bytes of a table up to which it is dealt out anew: files so small have few row groups.
SMALL_TABLE = 24 << 20


def spread(df: DataFrame) -> DataFrame:
    """A small table over all cores before work that costs more than its reading. Larger
    ones have row groups enough and stay as they are."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(df.sparkSession.sparkContext.defaultParallelism) if size <= SMALL_TABLE else df


#: Has Spark remove the shuffle files of a query when it ends.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, shared: list = ()) -> DataFrame:
    """A result that several parts of a plan read, computed once: a checkpoint where the
    session names a shared folder, else kept by the executors with its lineage. A checkpoint
    ends the query, so its shuffle files and the broadcasts ``shared`` are removed with it."""
    spark = df.sparkSession
    if not spark.sparkContext.getCheckpointDir():
        return df.persist()
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        out = df.select("*").checkpoint()  # the setting holds for frames that are made under it
    finally:
        spark.conf.set(_CLEANUP, before)
    for b in shared:
        b.destroy()
    return out


def sized_broadcast(df: DataFrame, most_rows: int) -> DataFrame:
    """Broadcast hint where a count shows that the side is small; else Spark shuffles."""
    return F.broadcast(df) if df.count() <= most_rows else df


def share(part: Column, whole: Column) -> Column:
    return F.when(whole != 0, part / whole)
