"""SQL surface: the tables as views, the methods' functions under their names."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..functions import answers as A
from .tables import load

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: Functions that are expressions: inlined by the optimizer, no Python.
SQL_FUNCTIONS = {
    "norm_text(x STRING) RETURNS STRING": r"trim(regexp_replace(regexp_replace(regexp_replace(lower(x), '\\\\[a-z]+', ' '), '[$(){}\\[\\],]', ' '), '[ \\t\\n\\r\\f]+', ' '))",
    "word_tokens(x STRING) RETURNS ARRAY<STRING>": r"regexp_extract_all(x, '[\\p{L}\\p{N}_]+', 0)",
    "set_jaccard(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE": "CASE WHEN size(a) = 0 OR size(b) = 0 THEN 0D ELSE size(array_intersect(a, b)) / size(array_union(a, b)) END",
    "vector_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v) / sqrt(aggregate(a, 0D, (s, v) -> s + v * v)) / sqrt(aggregate(b, 0D, (s, v) -> s + v * v))",
    "close_to(p DOUBLE, g DOUBLE, tol DOUBLE) RETURNS BOOLEAN": "coalesce(CASE WHEN g = 0 THEN abs(p) <= 1e-9 ELSE abs(p - g) <= tol * abs(g) + 1e-12 END, false)",
}


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Temporary views of the tables in ``sf_dir`` and temporary functions."""
    if sf_dir:
        for t in TABLES:
            load(spark, sf_dir, t).createOrReplaceTempView(t)
    for head, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    for name, f in (("last_boxed", A.last_boxed), ("all_boxed", A.all_boxed), ("evaluate_answer", A.evaluated), ("symbolic_match", A.symbolic_match)):
        spark.udf.register(name, f)
