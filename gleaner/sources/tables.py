"""Reading and writing quantitative databases."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gleaner.sources.shared import shared_dir

QDB = "tid long, item long, w long"
NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table, with the named columns alone if any are named."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """``df`` written as csv, json, orc or parquet and read again with its own schema."""
    import uuid

    path = f"{shared_dir(df.sparkSession)}/{kind}-{uuid.uuid4().hex}"
    df.write.format(kind).save(path)
    return df.sparkSession.read.format(kind).schema(df.schema).load(path)


def write_sparse(qdb: DataFrame, path: str) -> None:
    """One line for each transaction: ``items:total:utilities``, numbers parted by blanks."""
    row = F.array_sort(F.collect_list(F.struct("item", "w")))
    line = F.concat_ws(":", F.array_join(F.transform("r", lambda x: x["item"].cast("string")), " "), F.col("s").cast("string"), F.array_join(F.transform("r", lambda x: x["w"].cast("string")), " "))
    qdb.groupBy("tid").agg(row.alias("r"), F.sum("w").alias("s")).select(line.alias("value")).write.text(path)


def read_sparse(spark: SparkSession, path: str) -> DataFrame:
    """(tid, item, w) of lines ``items:total:utilities``. A transaction's id is the hash of its line and its number among equal lines."""
    part = F.split("value", ":")
    lines = spark.read.text(path).groupBy("value").agg(F.count("*").alias("times")).select("value", F.explode(F.sequence(F.lit(1).cast("long"), "times")).alias("copy"))
    lines = lines.select(F.xxhash64("value", "copy").alias("tid"), F.split(part[0], " ").alias("items"), F.split(part[2], " ").alias("ws"))
    return lines.select("tid", F.explode(F.arrays_zip("items", "ws")).alias("x")).select("tid", F.col("x.items").cast("long").alias("item"), F.col("x.ws").cast("long").alias("w"))


def write_triples(triples: DataFrame, path: str) -> None:
    triples.select(F.format_string("<%s> <%s> <%s> .", "s", "p", "o").alias("value")).write.text(path)


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o) of lines ``<s> <p> <o> .``"""
    grab = lambda k: F.regexp_extract("value", r"^<([^>]*)>\s+<([^>]*)>\s+<([^>]*)>\s*\.", k)
    return spark.read.text(path).where(F.col("value").startswith("<")).select(grab(1).alias("s"), grab(2).alias("p"), grab(3).alias("o"))


def bucket_of(tid: str, buckets: int) -> Column:
    return F.pmod(F.xxhash64(tid), F.lit(buckets)).cast("int").alias("bucket")


def write_weights(weights: DataFrame, path: str, buckets: int = 16) -> None:
    """Weights laid out by bucket, so that drawing reads only the buckets hit."""
    weights.select("*", bucket_of("tid", buckets)).repartition("bucket").sortWithinPartitions("tid").write.partitionBy("bucket").parquet(path)


def write_qdb(qdb: DataFrame, path: str, buckets: int = 64) -> None:
    """A database laid out by bucket of tid, one folder each, in the order of tid and item; the number of buckets stands in the path's ``_buckets``."""
    qdb.select("tid", "item", "w", bucket_of("tid", buckets)).repartition(buckets, "bucket").sortWithinPartitions("bucket", "tid", "item").write.partitionBy("bucket").parquet(path)
    qdb.sparkSession.range(1).select(F.lit(buckets).alias("buckets")).write.parquet(f"{path}/_buckets")  # Spark overlooks names that begin so


def buckets_in(path: str, spark: SparkSession) -> int:
    return spark.read.parquet(f"{path}/_buckets").first().buckets


def synthetic(spark: SparkSession, transactions: int | DataFrame, items: int, mean_length: int = 50, seed: int = 0) -> DataFrame:
    """(tid, item, w) with replayable hashes: about ``mean_length`` different items, weights 10 to 1000. ``transactions``: their number, or a table (tid)."""
    base = spark.range(transactions).withColumnRenamed("id", "tid") if isinstance(transactions, int) else transactions.select("tid")
    size = F.pmod(F.xxhash64("tid", F.lit(seed)), F.lit(mean_length)) + mean_length // 2
    rows = base.select("tid", F.explode(F.sequence(F.lit(1).cast("long"), size)).alias("k"))
    rows = rows.select("tid", F.pmod(F.xxhash64("tid", "k", F.lit(seed)), F.lit(items)).alias("item"), (F.pmod(F.xxhash64("k", "tid", F.lit(seed + 1)), F.lit(991)) + 10).alias("w"))
    return rows.groupBy("tid", "item").agg(F.min("w").alias("w"))
