"""Exact duplicates by skew-safe combining, in DataFrame functions only.

Three stages, each grouping by digest *and* whole normalised text, so a digest clash never joins two texts:
map tasks combine their own rows (partial aggregation), salted digest groups are merged, and the winners of the
salts are combined globally. A group of any size reaches a reducer as one row per map task or per salt.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gleaner.llm.common import named, row_hash
from gleaner.sources.shared import written

#: What counts as white space, and what a run of it becomes.
SPACE_RUN, SPACE = r"[\x20\x09-\x0D]+", " "
SALTS = 8


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_RUN, SPACE)


def sha256(text: Column) -> Column:
    return F.sha2(text.cast("binary"), 256)


def exact_groups(docs: DataFrame, salts: int = SALTS, digest: Callable[[Column], Column] = sha256) -> DataFrame:
    """One row per distinct normalised text: (digest, variant, keep_id, group_size, text).

    ``variant`` numbers the texts that share a digest; it is null where a digest has one text only.
    """
    norm = docs.select("doc_id", normalised(F.col("text")).alias("norm")).select("doc_id", "norm", digest(F.col("norm")).alias("digest"))
    salted = norm.groupBy("digest", F.pmod(F.xxhash64("doc_id"), F.lit(salts)).alias("salt"), "norm").agg(F.min("doc_id").alias("keep_id"), F.count("*").alias("n"))
    return salted.groupBy("digest", "norm").agg(F.min("keep_id").alias("keep_id"), F.sum("n").alias("group_size"))


def exact_dedup(docs: DataFrame, salts: int = SALTS, digest: Callable[[Column], Column] = sha256) -> DataFrame:
    """Decisions for every row of ``docs`` (doc_id, text): doc_id, keep_id, group_size, kept, text_sha256.

    Null text counts as empty. Texts are equal when they are the same after each run of ASCII white space became
    one space. Rows that repeat the smallest doc_id of a group are all marked kept (they are one document); a null
    doc_id is larger than any other. Other columns are not read. An empty table gives an empty one.
    """
    groups = written(exact_groups(docs, salts, digest).select("digest", "keep_id", "group_size", F.lit(None).cast("string").alias("norm")) if digest is sha256 else exact_groups(docs, salts, digest), "exact")
    rows = docs.select("doc_id", normalised(F.col("text")).alias("norm"))
    rows = rows.select("doc_id", digest(F.col("norm")).alias("digest"), sha256(F.col("norm")).alias("text_sha256"), "norm")
    clashes = groups.groupBy("digest").agg(F.count("*").alias("texts")).where("texts > 1").select("digest")
    out = ["doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"]
    if clashes.isEmpty():
        return rows.drop("norm").join(groups.drop("norm"), "digest").select(*out)
    if digest is sha256:
        raise RuntimeError("two texts share a SHA-256 digest: call exact_dedup with another digest")
    return rows.join(groups, ["digest", "norm"]).select(*out)


def drop_exact(docs: DataFrame, salts: int = SALTS) -> DataFrame:
    """``docs`` with all its columns, less the later copies; of repeated rows of one doc_id and text one stays.

    Null text counts as empty, a null doc_id as larger than any other; other columns may have any type or name; which of the
    rows that agree in doc_id and text stays is told by a hash of all columns; an empty table gives an empty one.
    """
    gone = exact_dedup(docs.select("doc_id", "text"), salts).where("not kept").select(F.col("doc_id").alias("__gleaner_gone_id"), F.col("text_sha256").alias("__gleaner_gone_sha")).distinct()
    keyed = docs.select("*", sha256(normalised(F.col("text"))).alias("__gleaner_sha"), row_hash(docs).alias("__gleaner_row"))
    kept = keyed.join(gone, F.col("doc_id").eqNullSafe(F.col("__gleaner_gone_id")) & (F.col("__gleaner_sha") == F.col("__gleaner_gone_sha")), "left_anti")
    first = F.row_number().over(Window.partitionBy("doc_id", "__gleaner_sha").orderBy("__gleaner_row"))
    return kept.withColumn("__gleaner_n", first).where("__gleaner_n = 1").select(*named(docs))
