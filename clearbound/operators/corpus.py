"""Curation and release: one schema, vocabularies, licences, splitting, pages, diffs, cards."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Closed vocabularies of the annotations.
VOCABULARY = {
    "difficulty": (1, 2, 3, 4, 5), "length": ("S", "M", "L"), "language": ("en", "de", "fr", "es"),
    "problem_type": ("mcq", "numeric", "multipart", "symbolic"), "math_level": ("none", "arithmetic", "algebra", "calculus", "beyond"), "modality": ("text", "image"),
    "licence": ("apache", "mit", "gpl", "cc-by", "reserved", "none"),
}


def unify(*frames: DataFrame) -> DataFrame:
    """Source families under one schema; fields a family lacks are null."""
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), frames)


def violations(df: DataFrame, fields: dict[str, tuple] | None = None) -> DataFrame:
    """Adds violations: the names of fields whose value is outside their vocabulary. Null counts as one."""
    own = {k: v for k, v in (fields or VOCABULARY).items() if k in df.columns}
    bad = [F.when(~F.coalesce(F.col(k).isin(*v), F.lit(False)), F.lit(k)) for k, v in own.items()]
    return df.withColumn("violations", F.array_compact(F.array(*bad)))


def licence_of(text: Column) -> Column:
    """Licence tag of a text by the line that states it."""
    low = F.lower(text)
    return (
        F.when(low.contains("apache license"), "apache").when(low.contains("mit license"), "mit").when(low.contains("gnu general public") | low.contains("gpl"), "gpl")
        .when(low.contains("creative commons") | low.contains("cc by"), "cc-by").when(low.contains("all rights reserved"), "reserved").otherwise("none")
    )


def commercial_ok(licence: Column) -> Column:
    return licence.isin("apache", "mit", "cc-by", "none")


PATTERNS = {"lines": r"[^\n]+", "sentences": r"[^.!?\n]+[.!?]?"}


def split_records(df: DataFrame, pattern: str, key: str = "doc_id") -> DataFrame:
    """key, pos, text: the pieces that a pattern finds."""
    return df.select(key, F.posexplode(F.regexp_extract_all("text", F.lit(pattern), F.lit(0))).alias("pos", "text"))


def splitter_recovery(df: DataFrame, key: str = "doc_id", least: int = 20) -> DataFrame:
    """Pieces of a useful length that each pattern recovers, and how many more than the first."""
    rows = []
    for name, p in PATTERNS.items():
        rows.append(split_records(df, p, key).where(F.length("text") >= least).agg(F.count(F.lit(1)).alias("pieces"), F.countDistinct(key).alias("docs")).select(F.lit(name).alias("splitter"), "pieces", "docs"))
    out = reduce(DataFrame.unionByName, rows)
    first = out.where(F.col("splitter") == next(iter(PATTERNS))).select(F.col("pieces").alias("_first"))
    return out.crossJoin(F.broadcast(first)).select("splitter", "pieces", "docs", (F.col("pieces") - F.col("_first")).alias("gain"))  # one row


def page_text(html: Column) -> Column:
    """Visible text of a page: scripts, styles and navigation, tags and entities out."""
    x = F.regexp_replace(html, r"(?i)<(script|style|nav)[^>]*>[\s\S]*?</(script|style|nav)>", " ")
    x = F.regexp_replace(F.regexp_replace(x, r"<[^>]+>", " "), r"&[a-z]+;|&#[0-9]+;", " ")
    return F.trim(F.regexp_replace(x, r"[ \t\n\r\f]+", " "))


def messages(turns: DataFrame) -> DataFrame:
    """conv_id, messages: the turns of each conversation in order. A conversation is bounded
    by its own turns."""
    m = F.array_sort(F.collect_list(F.struct("turn", "role", F.col("text").alias("content"))))
    return turns.groupBy("conv_id").agg(F.transform(m, lambda x: F.struct(x["role"].alias("role"), x["content"].alias("content"))).alias("messages"))


def version_diff(old: DataFrame, new: DataFrame, key: str, text: str = "text") -> DataFrame:
    """key, change: added, removed or changed, by digests."""
    a, b = (d.select(key, F.md5(text).alias(n)) for d, n in ((old, "_a"), (new, "_b")))
    j = a.join(b, key, "full")
    change = F.when(F.col("_a").isNull(), "added").when(F.col("_b").isNull(), "removed").when(F.col("_a") != F.col("_b"), "changed")
    return j.select(key, change.alias("change")).where("change is not null")


def card(df: DataFrame, name: str, version: str, licence: Column) -> DataFrame:
    """One JSON object that describes a release."""
    rows = df.groupBy(licence.alias("licence")).count()
    total = df.agg(F.count(F.lit(1)).alias("records"), F.countDistinct("source").alias("sources"))
    by = rows.agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("licence", "count")))).alias("licences"))  # one entry a licence
    return total.crossJoin(by).select(F.to_json(F.struct(F.lit(name).alias("name"), F.lit(version).alias("version"), "records", "sources", "licences")).alias("card"))


def bump(old: str, breaking: bool, additive: bool) -> str:
    """Version after a change: breaking, additive or corrections only."""
    major, minor, patch = map(int, old.split("."))
    return f"{major + 1}.0.0" if breaking else f"{major}.{minor + 1}.0" if additive else f"{major}.{minor}.{patch + 1}"
