"""Quantitative databases made from the given tables: (tid, item, qty[, price_cents], w)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gleaner.sources.tables import load

#: The worked example: triples, their counts, and prices of the variant whose fourth price is 1.
TOY_ITEMS = {1: 22, 2: 12, 3: 25, 4: 34}
TOY_PRICES = {1: 2, 2: 1, 3: 3, 4: 1}
TOY_TRANSACTIONS = {1: (1, 2, 3, 4), 2: (1,), 3: (2,), 4: (3, 4)}


def toy(spark: SparkSession, fourth_price: int = 1) -> DataFrame:
    prices = TOY_PRICES | {4: fourth_price}
    rows = [(t, i, TOY_ITEMS[i] * prices[i]) for t, items in TOY_TRANSACTIONS.items() for i in items]
    return spark.createDataFrame(rows, "tid long, item long, w long")


def basket(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by part: bought quantity times retail price in cents. One exchange, by order and part."""
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity").groupBy("l_orderkey", "l_partkey").agg(F.sum("l_quantity").cast("long").alias("qty"))
    parts = load(spark, sf_dir, "part", "p_partkey", "p_retailprice").select("p_partkey", F.round(F.col("p_retailprice") * 100).cast("long").alias("price_cents"))
    joined = lines.join(parts, lines.l_partkey == parts.p_partkey)
    return joined.select(F.col("l_orderkey").alias("tid"), F.col("l_partkey").alias("item"), "qty", "price_cents", (F.col("qty") * F.col("price_cents")).alias("w"))


def shopper(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers by part."""
    owner = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    rows = basket(spark, sf_dir).join(owner, F.col("tid") == F.col("o_orderkey"))
    return rows.groupBy(F.col("o_custkey").alias("tid"), "item").agg(F.sum("w").alias("w"))


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey", "l_quantity")
    return lines.groupBy(F.col("l_suppkey").alias("tid"), F.col("l_partkey").alias("item")).agg(F.sum("l_quantity").cast("long").alias("w"))


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users by the number in the events' JSON."""
    rows = load(spark, sf_dir, "events", "user_id", "props", "value").where("value > 0")
    return rows.groupBy(F.col("user_id").alias("tid"), F.get_json_object("props", "$.k").cast("long").alias("item")).agg(F.sum(F.col("value").cast("decimal(38,6)")).alias("w"))


def visit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user, day) by kind of event."""
    rows = load(spark, sf_dir, "events", "user_id", "ts", "event_type", "value").where("value > 0")
    tid = F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    return rows.groupBy(tid.alias("tid"), F.col("event_type").alias("item")).agg(F.sum(F.col("value").cast("decimal(38,6)")).alias("w"))


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents by word, counted."""
    rows = load(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), 1)).alias("item"))
    return rows.groupBy(F.col("doc_id").alias("tid"), "item").agg(F.count("*").alias("w"))


def dialog(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "conversations", "conv_id", "text").select("conv_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), 1)).alias("item"))
    return rows.groupBy(F.col("conv_id").alias("tid"), "item").agg(F.count("*").alias("w"))


def vector(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings by dimension with a positive value."""
    rows = load(spark, sf_dir, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("tid"), F.posexplode("embedding").alias("d", "w"))
    return rows.where("w > 0").select("tid", F.col("d").cast("long").alias("item"), F.col("w").cast("double").alias("w"))


def census(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by ten attributes, each with a fixed weight from its hash."""
    o = load(spark, sf_dir, "orders")
    c = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")
    n, r = load(spark, sf_dir, "nation", "n_nationkey", "n_name", "n_regionkey"), load(spark, sf_dir, "region", "r_regionkey", "r_name")
    j = o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    says = {
        "status": "o_orderstatus", "priority": "o_orderpriority", "year": "cast(year(o_orderdate) as string)", "month": "cast(month(o_orderdate) as string)",
        "weekday": "cast(weekday(o_orderdate) as string)", "band": "cast(cast(floor(o_totalprice / 50000) as bigint) as string)", "segment": "c_mktsegment", "nation": "n_name",
        "region": "r_name", "balance": "cast(cast(floor(c_acctbal / 2500) as bigint) as string)",
    }
    item = F.explode(F.array(*[F.expr(f"concat('{k}=', {v})") for k, v in says.items()])).alias("item")
    rows = j.select(F.col("o_orderkey").alias("tid"), item)
    return rows.select("tid", "item", (F.pmod(F.conv(F.substring(F.md5("item"), 1, 8), 16, 10).cast("long"), F.lit(991)) + 10).alias("w"))


def brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers by brand: quantities bought."""
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity")
    owner, part = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), load(spark, sf_dir, "part", "p_partkey", "p_brand")
    rows = lines.join(owner, lines.l_orderkey == owner.o_orderkey).join(part, lines.l_partkey == part.p_partkey)
    return rows.groupBy(F.col("o_custkey").alias("tid"), F.col("p_brand").alias("item")).agg(F.sum("l_quantity").cast("long").alias("w"))


def schema_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(subj, pred, obj, weight): class-level links of the star schema."""
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderpriority")
    line, p = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey"), load(spark, sf_dir, "part", "p_partkey", "p_brand")
    s, n, r = load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    say = lambda kind, column: F.concat(F.lit(f"{kind}|"), F.col(column))
    link = lambda df, a, pred, b: df.groupBy(a.alias("subj"), F.lit(pred).alias("pred"), b.alias("obj")).agg(F.count("*").alias("weight"))
    return (
        link(c.join(o, c.c_custkey == o.o_custkey), say("Customer", "c_mktsegment"), "places", say("Order", "o_orderpriority"))
        .unionByName(link(line.join(o, line.l_orderkey == o.o_orderkey).join(p, line.l_partkey == p.p_partkey), say("Order", "o_orderpriority"), "contains", say("Part", "p_brand")))
        .unionByName(link(line.join(p, line.l_partkey == p.p_partkey).join(s, line.l_suppkey == s.s_suppkey).join(n, s.s_nationkey == n.n_nationkey), say("Part", "p_brand"), "suppliedFrom", say("Nation", "n_name")))
        .unionByName(link(c.join(n, c.c_nationkey == n.n_nationkey), say("Customer", "c_mktsegment"), "livesIn", say("Nation", "n_name")))
        .unionByName(link(n.join(r, n.n_regionkey == r.r_regionkey), say("Nation", "n_name"), "partOf", say("Region", "r_name")))
    )


def link_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(subj, pred, obj, weight): hosts of pages and what they link to."""
    pages = load(spark, sf_dir, "pages", "url", "html")
    rows = pages.select(F.regexp_extract("url", r"://([^/]+)", 1).alias("subj"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("obj"))
    return rows.groupBy("subj", F.lit("linksTo").alias("pred"), "obj").agg(F.count("*").alias("weight"))
