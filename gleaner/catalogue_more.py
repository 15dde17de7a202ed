"""Queries of the operators around the methods: sources, joins, aggregates, windows, sets, functions, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gleaner.catalogue import _PREFIX, _SIZES, CHOOSE, K, QDB, SEED, TX, _jump_sql, _sizes_of, _uniform_sql, basket, query
from gleaner.functions import chance
from gleaner.operators import encode, mining, model, sampler
from gleaner.sources import tables
from gleaner.sources.shared import shared_dir
from gleaner.streaming import transactions as st

# --- sources and sinks --------------------------------------------------------------------------------------------


@query("scan_parquet_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS rows FROM {t}" for t in tables.NAMES))
def _(s: SparkSession, d: str) -> DataFrame:
    parts = [tables.load(s, d, t).agg(F.lit(t).alias("name"), F.count("*").alias("rows")).select("name", "rows") for t in tables.NAMES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


for _kind in ("csv", "json", "orc"):
    query(f"scan_roundtrip_{_kind}", QDB["basket"])(lambda s, d, kind=_kind: tables.round_trip(encode.basket(s, d), kind))


@query("scan_sparse_text", f"WITH q AS ({QDB['basket']}) SELECT item, CAST(sum(w) AS BIGINT) AS w, count(*) AS n FROM q GROUP BY item")
def _(s: SparkSession, d: str) -> DataFrame:
    path = f"{shared_dir(s)}/sparse-{uuid.uuid4().hex}"
    tables.write_sparse(basket(s, d), path)
    return tables.read_sparse(s, path).groupBy("item").agg(F.sum("w").alias("w"), F.count("*").alias("n"))


@query("scan_triples_text", "SELECT 'n' || n_nationkey AS s, 'partOf' AS p, 'r' || n_regionkey AS o FROM nation")
def _(s: SparkSession, d: str) -> DataFrame:
    path = f"{shared_dir(s)}/triples-{uuid.uuid4().hex}"
    tables.write_triples(tables.load(s, d, "nation").select(F.concat(F.lit("n"), "n_nationkey").alias("s"), F.lit("partOf").alias("p"), F.concat(F.lit("r"), "n_regionkey").alias("o")), path)
    return tables.read_triples(s, path)


@query("sink_bucketed_weights", f"{TX} SELECT count(*) AS transactions, CAST(sum(s) AS BIGINT) AS s FROM t")
def _(s: SparkSession, d: str) -> DataFrame:
    path = f"{shared_dir(s)}/weights-{uuid.uuid4().hex}"
    tables.write_weights(model.weights(basket(s, d)), path)
    return s.read.parquet(path).agg(F.count("*").alias("transactions"), F.sum("s").alias("s"))


query("synthetic_stats", None)(lambda s, d: model.sizes(tables.synthetic(s, tables.load(s, d, "customer", F.col("c_custkey").alias("tid")), 5000)).agg(F.count("*").alias("transactions"), F.avg("n").alias("n_avg")))

# --- projections, filters, joins ----------------------------------------------------------------------------------

query("proj_weight", "SELECT l_orderkey AS tid, l_partkey AS item, l_quantity * p_retailprice AS w FROM lineitem JOIN part ON l_partkey = p_partkey")(
    lambda s, d: model.weigh(tables.load(s, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity").toDF("tid", "item", "qty"), tables.load(s, d, "part", "p_partkey", "p_retailprice"))
)
query("filter_positive", "SELECT user_id AS tid, event_type AS item, round(sum(value), 4) AS w FROM events WHERE value > 0 GROUP BY 1, 2")(
    lambda s, d: model.validate(tables.load(s, d, "events").select(F.col("user_id").alias("tid"), F.col("event_type").alias("item"), F.col("value").alias("w"))).select("tid", "item", F.round("w", 4).alias("w"))
)
query("filter_items", f"WITH q AS ({QDB['brands']}) SELECT * FROM q WHERE item NOT IN (SELECT p_brand FROM part WHERE p_size = 1 GROUP BY 1 HAVING count(*) > 1)")(
    lambda s, d: model.restrict(encode.brands(s, d), deny=tables.load(s, d, "part").where("p_size = 1").groupBy(F.col("p_brand").alias("item")).agg(F.count("*").alias("c")).where("c > 1")).select("tid", "item", "w")
)
query("deny_list_weights", f"WITH q AS ({QDB['words']}), l AS (SELECT doc_id FROM labels WHERE quality = 1) SELECT tid, count(*) AS n FROM q WHERE tid IN (SELECT doc_id FROM l) GROUP BY tid")(
    lambda s, d: model.sizes(encode.words(s, d).join(tables.load(s, d, "labels").where("quality = 1").select(F.col("doc_id").alias("tid")), "tid", "left_semi")).select("tid", F.col("n").cast("long").alias("n"))
)
query("filter_len_ge_m", f"{TX} SELECT tid, n FROM t WHERE n >= 3")(lambda s, d: model.sizes(basket(s, d)).where("n >= 3").select("tid", F.col("n").cast("long").alias("n")))
query("join_broadcast_price", "SELECT l_partkey AS item, round(sum(l_quantity * p_retailprice), 2) AS w FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")(
    lambda s, d: tables.load(s, d, "lineitem", "l_partkey", "l_quantity").join(tables.load(s, d, "part", "p_partkey", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("l_partkey").alias("item")).agg(F.round(F.sum(F.col("l_quantity") * F.col("p_retailprice")), 2).alias("w"))
)
query("join_sortmerge_basket", "SELECT o_custkey AS tid, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(
    lambda s, d: tables.load(s, d, "lineitem", "l_orderkey").join(tables.load(s, d, "orders", "o_orderkey", "o_custkey").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_custkey").alias("tid")).agg(F.count("*").alias("n"))
)
query("join_shuffle_hash", "SELECT s_nationkey AS tid, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")(
    lambda s, d: tables.load(s, d, "lineitem", "l_suppkey").join(tables.load(s, d, "supplier", "s_suppkey", "s_nationkey").hint("shuffle_hash"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy(F.col("s_nationkey").alias("tid")).agg(F.count("*").alias("n"))
)
query("join_left_missing_price", "SELECT l_partkey AS item, CAST(sum(l_quantity * coalesce(p_size, 1)) AS BIGINT) AS w FROM lineitem LEFT JOIN (SELECT * FROM part WHERE p_size > 10) ON l_partkey = p_partkey GROUP BY 1")(
    lambda s, d: model.weigh(tables.load(s, d, "lineitem").select(F.col("l_orderkey").alias("tid"), F.col("l_partkey").alias("item"), F.col("l_quantity").alias("qty")), tables.load(s, d, "part", "p_partkey", "p_size").where("p_size > 10")).groupBy("item").agg(F.sum("w").cast("long").alias("w"))
)
query("join_full_price_diff", "SELECT coalesce(a.p_partkey, b.p_partkey) AS item, a.p_size AS old, b.p_size AS new FROM (SELECT * FROM part WHERE p_size > 10) a FULL JOIN (SELECT * FROM part WHERE p_size < 40) b ON a.p_partkey = b.p_partkey")(
    lambda s, d: (p := tables.load(s, d, "part", "p_partkey", "p_size")).where("p_size > 10").select(F.col("p_partkey").alias("item"), F.col("p_size").alias("old")).join(p.where("p_size < 40").select(F.col("p_partkey").alias("item"), F.col("p_size").alias("new")), "item", "full")
)
query("join_semi_picked", "SELECT l_orderkey AS tid, count(*) AS n FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT') GROUP BY 1")(
    lambda s, d: tables.load(s, d, "lineitem", "l_orderkey").join(tables.load(s, d, "orders").where("o_orderpriority = '1-URGENT'").select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey", "left_semi").groupBy(F.col("l_orderkey").alias("tid")).agg(F.count("*").alias("n"))
)
query("join_anti_unused_orders", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")(
    lambda s, d: tables.load(s, d, "orders", "o_orderkey").join(tables.load(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti")
)


@query("join_range_cumweight", f"{TX}, c AS (SELECT tid, tid % 64 AS b, sum(s) OVER o AS hi, sum(s) OVER o - s AS lo FROM t WINDOW o AS (PARTITION BY tid % 64 ORDER BY tid)), m AS (SELECT b, max(hi) AS z FROM c GROUP BY b) SELECT m.b AS bucket, k, tid FROM m, range(1, 11) r(k), c WHERE c.b = m.b AND k * z / 11.0 > lo AND k * z / 11.0 <= hi")
def _(s: SparkSession, d: str) -> DataFrame:
    per = model.sizes(basket(s, d)).withColumn("bucket", F.pmod("tid", F.lit(64)))
    run = F.sum("s").over(Window.partitionBy("bucket").orderBy("tid").rowsBetween(Window.unboundedPreceding, 0))
    spans = per.withColumn("hi", run).withColumn("lo", F.col("hi") - F.col("s")).select("bucket", "tid", "lo", "hi")
    points = per.groupBy("bucket").agg(F.sum("s").alias("z")).select("bucket", "z", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(10).cast("long"))).alias("k"))
    x = F.col("k") * F.col("z") / 11.0
    return points.join(spans, "bucket").where((x > F.col("lo")) & (x <= F.col("hi"))).select("bucket", "k", "tid")


@query("join_nested_loop_buckets", f"{TX}, z AS (SELECT tid % 16 AS b, sum(s) AS z FROM t GROUP BY 1), e AS (SELECT b, sum(z) OVER (ORDER BY b) AS hi, sum(z) OVER (ORDER BY b) - z AS lo FROM z), w AS (SELECT max(hi) AS z FROM e) SELECT k, b AS bucket FROM range(1, 101) r(k), e, w WHERE k * z / 101.0 > lo AND k * z / 101.0 <= hi")
def _(s: SparkSession, d: str) -> DataFrame:
    z = model.sizes(basket(s, d)).groupBy(F.pmod("tid", F.lit(16)).alias("bucket")).agg(F.sum("s").alias("z"))
    below = z.select(F.col("bucket").alias("b2"), F.col("z").alias("z2"))
    ends = z.join(F.broadcast(below), F.col("b2") <= F.col("bucket")).groupBy("bucket", "z").agg(F.sum("z2").alias("hi")).withColumn("lo", F.col("hi") - F.col("z"))  # 16 rows
    total = z.agg(F.sum("z").alias("total"))
    points = s.range(1, 101).withColumnRenamed("id", "k").join(F.broadcast(total), F.lit(True))
    x = F.col("k") * F.col("total") / 101.0
    return points.join(F.broadcast(ends), (x > F.col("lo")) & (x <= F.col("hi"))).select("k", "bucket")


query("join_theta_growth", f"WITH q AS ({QDB['visit']}) SELECT a.item AS a, b.item AS b, count(*) AS support FROM q a JOIN q b ON a.tid = b.tid AND a.item < b.item GROUP BY 1, 2")(
    lambda s, d: mining.occurrences(encode.visit(s, d), 2, 2).groupBy(F.col("pattern")[0].alias("a"), F.col("pattern")[1].alias("b")).agg(F.count("*").alias("support"))
)


@query("join_interval_click_purchase", "SELECT c.user_id, count(*) AS pairs FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase' GROUP BY 1")
def _(s: SparkSession, d: str) -> DataFrame:
    e = tables.load(s, d, "events", "user_id", "ts", "event_type")
    c, p = e.where("event_type = 'click'"), e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("ts2"))
    return c.join(p, "user_id").where((F.col("ts2") > F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr("INTERVAL 1 HOUR"))).groupBy("user_id").agg(F.count("*").alias("pairs"))


@query("join_asof_price", "WITH p AS (SELECT user_id, ts, value FROM events WHERE event_type = 'purchase'), m AS (SELECT user_id, ts, max(value) AS value FROM p GROUP BY 1, 2), c AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click') SELECT event_id, value AS price FROM c ASOF LEFT JOIN m ON c.user_id = m.user_id AND c.ts >= m.ts")
def _(s: SparkSession, d: str) -> DataFrame:
    e = tables.load(s, d, "events", "event_id", "user_id", "ts", "event_type", "value")
    price = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("price")).select(F.lit(None).cast("long").alias("event_id"), "user_id", "ts", "price", F.lit(0).alias("late"))
    click = e.where("event_type = 'click'").select("event_id", "user_id", "ts", F.lit(None).cast("double").alias("price"), F.lit(1).alias("late"))
    last = F.last("price", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "late").rowsBetween(Window.unboundedPreceding, 0))
    return price.unionByName(click).withColumn("price", last).where("late = 1").select("event_id", "price")




@query("join_lateral_topitems", f"WITH q AS ({QDB['shopper']}) SELECT tid, item, w FROM (SELECT *, row_number() OVER (PARTITION BY tid ORDER BY w DESC, item) AS r FROM q) WHERE r <= 3")
def _(s: SparkSession, d: str) -> DataFrame:
    encode.shopper(s, d).createOrReplaceTempView("gleaner_shopper")
    return s.sql("SELECT t.tid, x.item, x.w FROM (SELECT DISTINCT tid FROM gleaner_shopper) t, LATERAL (SELECT item, w FROM gleaner_shopper q WHERE q.tid = t.tid ORDER BY w DESC, item LIMIT 3) x")


# --- aggregates ---------------------------------------------------------------------------------------------------

query("agg_tx_sum_count", f"{TX} SELECT tid, n, s FROM t")(lambda s, d: model.sizes(basket(s, d)).select("tid", F.col("n").cast("long").alias("n"), "s"))
query("agg_sort_based_collect", f"WITH q AS ({QDB['basket']}) SELECT tid, array_to_string(list(item ORDER BY item), ',') AS items FROM q GROUP BY tid")(lambda s, d: model.pack(basket(s, d)).select("tid", F.array_join(F.col("items").cast("array<string>"), ",").alias("items")))
query("agg_distinct_items", f"WITH q AS ({QDB['basket']}) SELECT count(DISTINCT item) AS items FROM q")(lambda s, d: basket(s, d).agg(F.countDistinct("item").alias("items")))
query("agg_approx_distinct", None)(lambda s, d: basket(s, d).agg(F.approx_count_distinct("item", 0.02).alias("items")))
from gleaner.catalogue import SCHEMA_TRIPLES  # noqa: E402

_T = f"WITH t AS ({SCHEMA_TRIPLES})"
query("agg_rollup_weight", f"{_T} SELECT pred, subj, CAST(sum(weight) AS BIGINT) AS weight FROM t GROUP BY ROLLUP (pred, subj)")(lambda s, d: encode.schema_triples(s, d).rollup("pred", "subj").agg(F.sum("weight").alias("weight")))
query("agg_cube_weight", "SELECT c_mktsegment AS segment, r_name AS region, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (c_mktsegment, r_name)")(
    lambda s, d: tables.load(s, d, "orders", "o_custkey").join(tables.load(s, d, "customer", "c_custkey", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey")).join(tables.load(s, d, "nation", "n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey")).join(tables.load(s, d, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey")).cube(F.col("c_mktsegment").alias("segment"), F.col("r_name").alias("region")).agg(F.count("*").alias("orders"))
)


@query("agg_grouping_sets", f"{_T} SELECT pred, obj, CAST(sum(weight) AS BIGINT) AS weight FROM t GROUP BY GROUPING SETS ((pred), (obj), ())")
def _(s: SparkSession, d: str) -> DataFrame:
    encode.schema_triples(s, d).createOrReplaceTempView("gleaner_triples")
    return s.sql("SELECT pred, obj, sum(weight) AS weight FROM gleaner_triples GROUP BY GROUPING SETS ((pred), (obj), ())")


query("agg_pivot_lengths", f"WITH j AS ({_jump_sql()}), e AS ({_uniform_sql('CAST(1 AS DOUBLE)')}), x AS (SELECT length, 'jump' AS m FROM j UNION ALL SELECT length, 'uniform' FROM e) SELECT length, count(*) FILTER (m = 'jump') AS jump, count(*) FILTER (m = 'uniform') AS uniform FROM x GROUP BY length")(
    lambda s, d: (sampler.sample(basket(s, d), K, seed=SEED, pick="prefix", engine="sql").select("length", F.lit("jump").alias("m")))
    .unionByName(sampler.uniform_patterns(basket(s, d), K, 1, 5, "length_first", SEED).select("length", F.lit("uniform").alias("m")))
    .groupBy(F.col("length").cast("long").alias("length")).pivot("m", ["jump", "uniform"]).agg(F.count(F.lit(1))).na.fill(0)
)
query("agg_percentiles", f"{TX} SELECT n, quantile_cont(s, 0.5) AS median, quantile_cont(s, 0.25) AS low FROM t GROUP BY n")(
    lambda s, d: model.sizes(basket(s, d)).groupBy(F.col("n").cast("long").alias("n")).agg(F.percentile("s", 0.5).alias("median"), F.percentile("s", 0.25).alias("low"))
)
query("agg_max_by_top_tx", f"{TX} SELECT n, arg_max(tid, s * 1000000 + tid) AS tid FROM t GROUP BY n")(lambda s, d: model.sizes(basket(s, d)).groupBy(F.col("n").cast("long").alias("n")).agg(F.max_by("tid", F.col("s") * 1000000 + F.col("tid")).alias("tid")))

# --- windows, sorts, sets -----------------------------------------------------------------------------------------

_by_item = lambda: Window.partitionBy("tid").orderBy("item")
query("win_prefix_sum", f"{_PREFIX} SELECT tid, item, s FROM p")(lambda s, d: basket(s, d).withColumn("s", F.sum("w").over(_by_item().rowsBetween(Window.unboundedPreceding, 0))).select("tid", "item", "s"))
query("win_position", f"{_PREFIX} SELECT tid, item, i FROM p")(lambda s, d: basket(s, d).withColumn("i", F.row_number().over(_by_item()).cast("long")).select("tid", "item", "i"))
query("win_lag_bounds", f"{_PREFIX} SELECT tid, item, lag(s, 1, 0) OVER (PARTITION BY tid ORDER BY item) AS lo, s AS hi FROM p")(
    lambda s, d: basket(s, d).withColumn("hi", F.sum("w").over(_by_item().rowsBetween(Window.unboundedPreceding, 0))).select("tid", "item", F.lag("hi", 1, 0).over(_by_item()).alias("lo"), "hi")
)
query("win_rank_patterns", f"WITH q AS ({QDB['brands']}) SELECT tid, item, rank() OVER o AS r, dense_rank() OVER o AS dr, ntile(4) OVER (PARTITION BY tid ORDER BY w DESC, item) AS q4, round(percent_rank() OVER o, 6) AS pr FROM q WINDOW o AS (PARTITION BY tid ORDER BY w DESC)")(
    lambda s, d: (lambda o: encode.brands(s, d).select("tid", "item", F.rank().over(o).cast("long").alias("r"), F.dense_rank().over(o).cast("long").alias("dr"), F.ntile(4).over(Window.partitionBy("tid").orderBy(F.desc("w"), "item")).cast("long").alias("q4"), F.round(F.percent_rank().over(o), 6).alias("pr")))(Window.partitionBy("tid").orderBy(F.desc("w")))
)
query("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW) AS n FROM events")(
    lambda s, d: tables.load(s, d, "events", "event_id", "user_id", "ts").withColumn("sec", F.unix_seconds(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("sec").rangeBetween(-604800, 0)).alias("n"))
)
query("sort_limit_topk", f"{TX} SELECT tid, s FROM t ORDER BY s DESC, tid LIMIT 25")(lambda s, d: model.sizes(basket(s, d)).orderBy(F.desc("s"), "tid").limit(25).select("tid", "s"))
_A, _B = "SELECT l_partkey AS item FROM lineitem WHERE l_returnflag = 'R'", "SELECT l_partkey AS item FROM lineitem WHERE l_linestatus = 'O'"
_sides = lambda s, d: [tables.load(s, d, "lineitem").where(c).select(F.col("l_partkey").alias("item")) for c in ("l_returnflag = 'R'", "l_linestatus = 'O'")]
query("set_union_samples", f"{_A} UNION {_B}")(lambda s, d: (lambda a, b: a.union(b).distinct())(*_sides(s, d)))
query("set_intersect", f"{_A} INTERSECT {_B}")(lambda s, d: (lambda a, b: a.intersect(b))(*_sides(s, d)))
query("set_except", f"{_A} EXCEPT {_B}")(lambda s, d: (lambda a, b: a.subtract(b))(*_sides(s, d)))
query("set_except_all", f"{_A} EXCEPT ALL {_B}")(lambda s, d: (lambda a, b: a.exceptAll(b))(*_sides(s, d)))

# --- functions ----------------------------------------------------------------------------------------------------

query("str_tokens", QDB["words"])(encode.words)
query("str_url_host", "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host FROM pages")(lambda s, d: tables.load(s, d, "pages", "page_id", "url").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host")))
query("str_href", "SELECT page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS links FROM pages")(lambda s, d: tables.load(s, d, "pages", "page_id", "html").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).cast("long").alias("links")))
query("date_visit_day", "SELECT user_id, count(DISTINCT date_trunc('day', ts)) AS days FROM events GROUP BY 1")(lambda s, d: tables.load(s, d, "events", "user_id", "ts").groupBy("user_id").agg(F.countDistinct(F.date_trunc("day", "ts")).alias("days")))


@query("math_log_binom", f"SELECT n, k, round(lgamma(n + 1) - lgamma(k + 1) - lgamma(n - k + 1), 6) AS v FROM ({_SIZES('shopper')}), LATERAL (SELECT unnest(range(0, n + 1)) AS k)")
def _(s: SparkSession, d: str) -> DataFrame:
    """Over the sizes of the shoppers' transactions."""
    chance.register(s)
    _sizes_of(s, d, "shopper").createOrReplaceTempView("gleaner_sizes")
    return s.sql("SELECT n, k, round(log_binom(cast(n AS INT), cast(k AS INT)), 6) + 0D AS v FROM (SELECT n, explode(sequence(0L, n)) AS k FROM gleaner_sizes)")


@query("math_prefix_mass", f"{TX}, m AS (SELECT n AS i, max(s) AS s FROM t GROUP BY n) SELECT l, i, round(ln({CHOOSE.format('i', 'l')} * (l * CAST(s AS DOUBLE) / i + 3)), 6) AS m FROM m, range(1, 31) a(l) WHERE l <= i")
def _(s: SparkSession, d: str) -> DataFrame:
    """Logarithms of the masses of every length over the heaviest basket of each size."""
    chance.register(s)
    model.sizes(basket(s, d)).groupBy(F.col("n").cast("long").alias("i")).agg(F.max("s").alias("s")).createOrReplaceTempView("gleaner_heaviest")
    return s.sql("SELECT l, i, round(ln(prefix_mass(cast(l AS INT), cast(i AS INT), cast(s AS DOUBLE), 3D)), 6) AS m FROM (SELECT explode(sequence(1L, i)) AS l, i, s FROM gleaner_heaviest)")


query("math_md5_uniform", f"SELECT o_orderkey, {chance.duck_uniform(str(SEED), 'o_orderkey', chr(39) + 'x' + chr(39))} AS u FROM orders")(lambda s, d: tables.load(s, d, "orders", "o_orderkey").select("o_orderkey", chance.uniform(SEED, F.col("o_orderkey"), "x").alias("u")))
query("arr_subset_test", f"WITH q AS ({QDB['brands']}), a AS (SELECT tid, list(item) AS items FROM q GROUP BY tid) SELECT tid, list_has_all(items, ['Brand#11', 'Brand#12']) AS has FROM a")(
    lambda s, d: encode.brands(s, d).groupBy("tid").agg(F.collect_list("item").alias("items")).select("tid", (F.size(F.array_except(F.array(F.lit("Brand#11"), F.lit("Brand#12")), "items")) == 0).alias("has"))
)
query("arr_jaccard", f"WITH q AS ({QDB['brands']}), a AS (SELECT tid, list(item) AS x FROM q GROUP BY tid) SELECT a.tid, round(len(list_intersect(a.x, b.x)) / len(list_distinct(list_concat(a.x, b.x))), 6) AS j FROM a JOIN a b ON b.tid = a.tid + 1")(
    lambda s, d: (lambda a: a.join(a.select((F.col("tid") - 1).alias("tid"), F.col("x").alias("y")), "tid").select("tid", F.round(F.size(F.array_intersect("x", "y")) / F.size(F.array_union("x", "y")), 6).alias("j")))(encode.brands(s, d).groupBy("tid").agg(F.collect_set("item").alias("x")))
)
query("map_tx_as_map", f"WITH q AS ({QDB['visit']}) SELECT tid, round(CAST(sum(w) FILTER (item = 'click') AS DOUBLE), 4) AS click, count(*) FILTER (w > 50) AS large FROM q GROUP BY tid")(
    lambda s, d: encode.visit(s, d).groupBy("tid").agg(F.map_from_entries(F.collect_list(F.struct("item", "w"))).alias("m")).select("tid", F.round(F.col("m")["click"].cast("double"), 4).alias("click"), F.size(F.map_filter("m", lambda k, v: v > 50)).cast("long").alias("large"))
)
query("json_props_key", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: tables.load(s, d, "events", "props").select(F.from_json("props", "k long").alias("j")).groupBy("j.k").agg(F.count("*").alias("n")))
query("vec_positive_dims", "SELECT vec_id AS tid, len(list_filter(embedding, lambda x: x > 0)) AS n FROM embeddings")(lambda s, d: model.sizes(encode.vector(s, d)).select("tid", F.col("n").cast("long").alias("n")))


@query("udtf_subsets", f"{TX} SELECT tid, l AS length, CAST({CHOOSE.format('n', 'l')} AS BIGINT) AS n FROM t, range(1, 4) r(l) WHERE l <= n")
def _(s: SparkSession, d: str) -> DataFrame:
    chance.register(s)
    model.pack(basket(s, d)).select("tid", "items").createOrReplaceTempView("gleaner_packed")
    return s.sql("SELECT tid, cast(length AS BIGINT) AS length, count(*) AS n FROM gleaner_packed, LATERAL subsets(items, 1, 3) GROUP BY tid, length")


@query("udtf_draws", None)
def _(s: SparkSession, d: str) -> DataFrame:
    chance.register(s)
    model.pack(basket(s, d)).createOrReplaceTempView("gleaner_long")
    return s.sql("SELECT tid, draw, pattern FROM gleaner_long, LATERAL draws(tid, items, w, 2)")


query("reweight_redraw", _jump_sql().replace(QDB["basket"], "SELECT l_orderkey AS tid, l_partkey AS item, CAST(sum(l_quantity) AS BIGINT) * p_size AS w FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_orderkey, l_partkey, p_size", 1))(
    lambda s, d: sampler.Sampler(encode.basket(s, d), seed=SEED).reweight(prices=tables.load(s, d, "part").select(F.col("p_partkey").alias("item"), F.col("p_size").cast("long").alias("price"))).sample(K, pick="prefix", engine="sql")
    .select("draw_id", "tid", F.expr("array_join(cast(pattern as array<string>), ',') AS pattern"), F.col("length").cast("long").alias("length"))
)
query("ablate_methods", None)(lambda s, d: _methods(s, d))


def _methods(s: SparkSession, d: str) -> DataFrame:
    """Mean length and utility share of each draw method under the same picks: all follow one law."""
    out = None
    for method in ("jump", "sequential", "seed", "matrix"):
        one = sampler.sample(basket(s, d), K, seed=SEED, method=method, pick="prefix").agg(F.lit(method).alias("method"), F.avg("length").alias("length"), F.countDistinct("pattern").alias("patterns"))
        out = one if out is None else out.unionByName(one)
    return out


# --- streams ------------------------------------------------------------------------------------------------------


def _closed(alias: str, step: str) -> str:
    return f"SELECT user_id, {step} AS start, event_type AS item, round(sum(value), 4) AS w FROM events WHERE value > 0 GROUP BY 1, 2, 3"


def _stream(s: SparkSession, d: str) -> DataFrame:
    """The given events, as files that arrive: one folder of Parquet."""
    path = f"{shared_dir(s)}/events-{uuid.uuid4().hex}"
    s.read.parquet(f"{d}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props").write.parquet(path)
    return st.events(s, path)


query("stream_tumbling_weights", None)(lambda s, d: st.replay(st.windowed(_stream(s, d), "tumbling")))
query("stream_sliding_weights", None)(lambda s, d: st.replay(st.windowed(_stream(s, d), "sliding", "2 days", "1 day")))
query("stream_session_weights", None)(lambda s, d: st.replay(st.windowed(_stream(s, d), "session", "6 hours")))
query("stream_dedup", "SELECT count(*) AS n FROM events WHERE value > 0")(lambda s, d: st.replay(_stream(s, d).select("event_id", "at")).agg(F.count("*").alias("n")))


@query("stream_reservoir", None)
def _(s: SparkSession, d: str) -> DataFrame:
    """Slots filled by the closed days of a stream."""
    held = st.Reservoir(50, SEED)

    def each(batch: DataFrame, number: int) -> None:
        rows = batch.select(F.xxhash64("user_id", "start").alias("tid"), "item", "w")
        held.add(model.weights(rows), number)

    st.replay(st.windowed(_stream(s, d), "tumbling"), each=each)
    return s.createDataFrame([(k, t, n) for k, (t, n) in sorted(held.slots.items())], "slot long, tid long, n int")


_DAY = "SELECT user_id, date_trunc('day', ts){0} AS start, event_type AS item, round(sum(value), 4) AS w FROM events{1} WHERE value > 0 GROUP BY 1, 2, 3"
_flat = lambda df: df.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "item", F.round("w", 4).alias("w"))
query("stream_thinned", f"SELECT event_id FROM events WHERE value > 0 AND {chance.duck_uniform(str(SEED), 'event_id')} < 0.25")(lambda s, d: st.replay(st.thinned(_stream(s, d), 0.25, SEED).select("event_id")))
query("replay_tumbling", _DAY.format("", ""))(lambda s, d: _flat(st.replay(st.windowed(_stream(s, d), "tumbling"), "complete")))
query("replay_sliding", _DAY.format(" - INTERVAL 1 DAY * back", ", range(2) r(back)"))(lambda s, d: _flat(st.replay(st.windowed(_stream(s, d), "sliding", "2 days", "1 day"), "complete")))
query("stream_join_click_purchase", "SELECT c.user_id, c.event_id, p.event_id AS other_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase' AND c.value > 0 AND p.value > 0")(
    lambda s, d: st.replay(st.pairs_within(*(_stream(s, d).where(f"event_type = '{k}'") for k in ("click", "purchase"))))
)


@query("stream_late_rows", None)
def _(s: SparkSession, d: str) -> DataFrame:
    """(late, kept): events of later days first, all others in a second batch, when the watermark has passed most of them."""
    rows = s.read.parquet(f"{d}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    middle = rows.agg(F.percentile(F.unix_seconds(F.col("ts").cast("timestamp")), 0.5)).first()[0]
    path = f"{shared_dir(s)}/late-{uuid.uuid4().hex}"
    late = F.unix_seconds(F.col("ts").cast("timestamp")) < middle
    for part, keep in enumerate((~late, late)):
        rows.where(keep).coalesce(1).write.mode("append").parquet(path)
    stream = st.events(s, path, "1 hour", files=1)
    out, dropped = st.replay_counted(stream.select("event_id", "at"))
    return out.agg(F.lit(dropped).cast("long").alias("late"), F.count("*").alias("kept"))


@query("stream_stateful_reservoir", None)
def _(s: SparkSession, d: str) -> DataFrame:
    """Closed days of a stream are written as they close; a second stream keeps slots of them in its state."""
    days = st.replay(st.windowed(_stream(s, d), "tumbling"))
    path = f"{shared_dir(s)}/days-{uuid.uuid4().hex}"
    model.weights(days.select(F.xxhash64("user_id", "start").alias("tid"), "item", "w")).select("tid", "n", "logw").write.parquet(path)
    seen: list[str] = []

    def each(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}-slots/{number}")
        seen.append(f"{path}-slots/{number}")

    st.replay(st.stored_reservoir(s.readStream.schema("tid long, n int, logw double").parquet(path), 50, SEED), "update", each)
    slots = s.read.parquet(*seen)
    newest = slots.groupBy("block", "slot").agg(F.max_by(F.struct("tid", "n", "log_total"), "batch").alias("x")).select("block", "slot", "x.*")
    return st.merged_slots(newest, SEED)


@query("udaf_reservoir", None)
def _(s: SparkSession, d: str) -> DataFrame:
    """One transaction in proportion to weight by a grouped aggregate in two levels: of blocks, then of their winners."""
    pick, total = chance.weighted_pick()
    w = model.weights(basket(s, d)).select(F.pmod("tid", F.lit(16)).alias("block"), "tid", "logw")
    level = w.groupBy("block").agg(pick("tid", "logw").alias("tid"), total("logw").alias("logw"))  # 16 rows
    return level.agg(pick("tid", "logw").alias("tid"))


query("tumbling_tx", _closed("day", "date_trunc('day', ts)"))(
    lambda s, d: tables.load(s, d, "events").where("value > 0").groupBy("user_id", F.window(F.col("ts").cast("timestamp"), "1 day").start.cast("timestamp_ntz").alias("start"), F.col("event_type").alias("item")).agg(F.round(F.sum("value"), 4).alias("w"))
)
query("session_tx", "WITH e AS (SELECT user_id, ts, event_type, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WHERE value > 0), g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, count(DISTINCT event_type) AS n, round(sum(value), 4) AS s FROM g GROUP BY user_id, k")(
    lambda s, d: tables.load(s, d, "events").where("value > 0").groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "6 hours")).agg(F.size(F.collect_set("event_type")).cast("long").alias("n"), F.round(F.sum("value"), 4).alias("s")).select("user_id", "n", "s")
)
query("sliding_tx", "SELECT user_id, date_trunc('day', ts) - INTERVAL 1 DAY * back AS start, count(DISTINCT event_type) AS n, round(sum(value), 4) AS s FROM events, range(2) r(back) WHERE value > 0 GROUP BY 1, 2")(
    lambda s, d: tables.load(s, d, "events").where("value > 0").groupBy("user_id", F.window(F.col("ts").cast("timestamp"), "2 days", "1 day").start.cast("timestamp_ntz").alias("start")).agg(F.size(F.collect_set("event_type")).cast("long").alias("n"), F.round(F.sum("value"), 4).alias("s"))
)
