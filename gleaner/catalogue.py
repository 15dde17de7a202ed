"""All queries of the library, by name, with DuckDB SQL that gives the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from math import factorial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gleaner.functions.chance import duck_uniform
from gleaner.operators import encode, experiments, jump, kg, matrix, metrics, mining, model, sampler
from gleaner.operators.lengths import MEAN, SUM, LengthUtility, coefficients, length_law, pascal_cells
from gleaner.sources import tables
from gleaner.sources.shared import shared_dir, written

_queries: dict[str, Callable] = {}
_sql: dict[str, str] = {}
K, SEED = 1000, 7


def query(name: str, sql: str | None = None):
    def add(f: Callable) -> Callable:
        _queries[name] = f
        if sql:
            _sql[name] = sql
        return f

    return add


def queries() -> dict[str, Callable]:
    import gleaner.catalogue_more  # noqa: F401

    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    import gleaner.catalogue_more  # noqa: F401

    return dict(_sql)


# --- the databases, in SQL ----------------------------------------------------------------------------------------

WORDS = r"regexp_extract_all(lower(text), '\p{L}+')"
QDB = {
    "basket": "SELECT l_orderkey AS tid, l_partkey AS item, CAST(sum(l_quantity) AS BIGINT) AS qty, CAST(round(p_retailprice * 100) AS BIGINT) AS price_cents, CAST(sum(l_quantity) AS BIGINT) * CAST(round(p_retailprice * 100) AS BIGINT) AS w FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY l_orderkey, l_partkey, p_retailprice",
    "shopper": "SELECT o_custkey AS tid, l_partkey AS item, CAST(sum(l_quantity * round(p_retailprice * 100)) AS BIGINT) AS w FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
    "supply": "SELECT l_suppkey AS tid, l_partkey AS item, CAST(sum(l_quantity) AS BIGINT) AS w FROM lineitem GROUP BY 1, 2",
    "activity": "SELECT user_id AS tid, CAST(json_extract_string(props, '$.k') AS BIGINT) AS item, sum(CAST(value AS DECIMAL(30, 6))) AS w FROM events WHERE value > 0 GROUP BY 1, 2",
    "visit": "SELECT concat_ws('|', user_id, strftime(ts, '%Y-%m-%d')) AS tid, event_type AS item, sum(CAST(value AS DECIMAL(30, 6))) AS w FROM events WHERE value > 0 GROUP BY 1, 2",
    "words": f"SELECT doc_id AS tid, item, count(*) AS w FROM (SELECT doc_id, unnest({WORDS}) AS item FROM documents) GROUP BY 1, 2",
    "dialog": f"SELECT conv_id AS tid, item, count(*) AS w FROM (SELECT conv_id, unnest({WORDS}) AS item FROM conversations) GROUP BY 1, 2",
    "vector": "SELECT vec_id AS tid, i - 1 AS item, CAST(embedding[i] AS DOUBLE) AS w FROM embeddings, range(1, 65) r(i) WHERE embedding[i] > 0",
    "brands": "SELECT o_custkey AS tid, p_brand AS item, CAST(sum(l_quantity) AS BIGINT) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2",
    "census": """SELECT tid, item, CAST(('0x' || substr(md5(item), 1, 8))::BIGINT % 991 + 10 AS BIGINT) AS w FROM (
        SELECT o_orderkey AS tid, unnest(['status=' || o_orderstatus, 'priority=' || o_orderpriority, 'year=' || year(o_orderdate), 'month=' || month(o_orderdate),
          'weekday=' || ((dayofweek(o_orderdate) + 6) % 7), 'band=' || CAST(floor(o_totalprice / 50000) AS BIGINT), 'segment=' || c_mktsegment, 'nation=' || n_name,
          'region=' || r_name, 'balance=' || CAST(floor(c_acctbal / 2500) AS BIGINT)]) AS item
        FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)""",
}
SCHEMA_TRIPLES = """
    SELECT 'Customer|' || c_mktsegment AS subj, 'places' AS pred, 'Order|' || o_orderpriority AS obj, count(*) AS weight FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1, 2, 3
    UNION ALL SELECT 'Order|' || o_orderpriority, 'contains', 'Part|' || p_brand, count(*) FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2, 3
    UNION ALL SELECT 'Part|' || p_brand, 'suppliedFrom', 'Nation|' || n_name, count(*) FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1, 2, 3
    UNION ALL SELECT 'Customer|' || c_mktsegment, 'livesIn', 'Nation|' || n_name, count(*) FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2, 3
    UNION ALL SELECT 'Nation|' || n_name, 'partOf', 'Region|' || r_name, count(*) FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2, 3"""
LINK_TRIPLES = """SELECT subj, 'linksTo' AS pred, obj, count(*) AS weight FROM (SELECT regexp_extract(url, '://([^/]+)', 1) AS subj, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS obj FROM pages) GROUP BY 1, 3"""
QDB["graph"] = f"SELECT tid, item, weight AS w FROM (WITH t AS ({SCHEMA_TRIPLES}) SELECT 'out|' || subj AS tid, subj || pred || obj AS item, weight FROM t UNION ALL SELECT 'in|' || obj, subj || pred || obj, weight FROM t)"
QDB["links"] = f"SELECT 'out|' || subj AS tid, subj || ' ' || obj AS item, weight AS w FROM ({LINK_TRIPLES})"
BUILD: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    k: getattr(encode, k) for k in ("basket", "shopper", "supply", "activity", "visit", "words", "dialog", "vector", "brands", "census")
} | {
    "graph": lambda s, d: kg.to_qdb(kg.simple_profile(encode.schema_triples(s, d))).withColumnRenamed("qty", "w"),
    "links": lambda s, d: kg.to_qdb(kg.simple_profile(encode.link_triples(s, d)), "out").withColumnRenamed("qty", "w"),
}
CHOOSE = "CAST(factorial(CAST({0} AS INTEGER)) // (factorial(CAST({1} AS INTEGER)) * factorial(CAST(({0}) - ({1}) AS INTEGER))) AS DOUBLE)"
TX = f"WITH q AS ({QDB['basket']}), t AS (SELECT tid, count(*) AS n, CAST(sum(w) AS BIGINT) AS s FROM q GROUP BY tid)"


def basket(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode.basket(spark, sf_dir).select("tid", "item", "w")


# --- databases and their sizes ------------------------------------------------------------------------------------

for _name in BUILD:
    query(
        f"qdb_stats_{_name}",
        f"WITH q AS ({QDB[_name]}), t AS (SELECT tid, count(*) AS n FROM q GROUP BY tid) SELECT count(*) AS transactions, CAST(sum(n) AS BIGINT) AS rows, min(n) AS n_min, max(n) AS n_max, (SELECT count(DISTINCT item) FROM q) AS items, round(sum(n) / count(*), 6) AS n_avg FROM t",
    )(lambda s, d, build=BUILD[_name]: metrics.qdb_stats(build(s, d)))

query("item_weight_basket", QDB["basket"])(encode.basket)
query("item_weight_census", QDB["census"])(encode.census)
query("profile_schema", SCHEMA_TRIPLES)(encode.schema_triples)
query("profile_links", LINK_TRIPLES)(encode.link_triples)


# --- weights ------------------------------------------------------------------------------------------------------


def _weights(f: LengthUtility, build: Callable = basket) -> Callable:
    return lambda s, d: model.weights(build(s, d), f).select("tid", F.col("n").cast("long").alias("n"), "s", F.round("w", 4).alias("w"))


def _interval(m: int, M: int | None, value: str = "1.0") -> str:  # noqa: N803
    top = "n" if M is None else f"least(n, {M})"
    return f"{TX}, c AS (SELECT n, sum({CHOOSE.format('n - 1', 'l - 1')} * {value}) AS c FROM (SELECT DISTINCT n FROM t), range(1, 30) r(l) WHERE l BETWEEN {m} AND {top} GROUP BY n) SELECT tid, n, s, round(s * c, 4) AS w FROM t JOIN c USING (n)"


query("tx_weight_sum_unbounded", f"{TX} SELECT tid, n, s, round(s * pow(2, n - 1), 4) AS w FROM t")(_weights(SUM))
query("tx_weight_mean_unbounded", f"{TX} SELECT tid, n, s, round(s * ((pow(2, n) - 1) / n), 4) AS w FROM t")(_weights(MEAN))
for _m in (2, 5, 10):
    query(f"tx_weight_interval_{_m}", _interval(1, _m))(_weights(LengthUtility("const", 1, _m)))
    query(f"tx_weight_mean_interval_{_m}", _interval(1, _m, "(1.0 / l)"))(_weights(LengthUtility("mean", 1, _m)))
query("tx_weight_min_len", _interval(3, None))(_weights(LengthUtility("const", 3)))
query("tx_weight_item_sampling", f"{TX} SELECT tid, n, s, round(s * 1.0, 4) AS w FROM t")(_weights(LengthUtility("const", 1, 1)))
query("tx_weight_decay", _interval(1, 6, "exp(-0.5 * l)"))(_weights(LengthUtility("decay", 1, 6, 0.5)))
query("tx_weight_power", _interval(1, 6, "pow(l, -2.0)"))(_weights(LengthUtility("power", 1, 6, 2.0)))


def _log_weights(name: str) -> str:
    return f"WITH q AS ({QDB[name]}), t AS (SELECT tid, count(*) AS n, sum(w) AS s FROM q GROUP BY tid) SELECT tid, n, round(ln(CAST(s AS DOUBLE)) + (n - 1) * ln(2), 6) AS logw FROM t"


for _name in ("words", "shopper", "supply", "activity", "dialog", "vector", "census", "graph"):
    query(f"tx_logweight_{_name}", _log_weights(_name))(
        lambda s, d, build=BUILD[_name]: model.weights(build(s, d)).select("tid", F.col("n").cast("long").alias("n"), F.round("logw", 6).alias("logw"))
    )

query("normaliser_basket", f"{TX} SELECT CAST(sum(s * pow(2, n - 1)) AS BIGINT) AS z FROM t")(lambda s, d: model.weights(basket(s, d)).agg(F.sum("w").cast("long").alias("z")))
query("agg_logsumexp", f"WITH w AS ({_log_weights('words')}), m AS (SELECT max(logw) AS top FROM w) SELECT round(top + ln(sum(exp(logw - top))), 4) AS log_total FROM w, m GROUP BY top")(
    lambda s, d: model.log_sum_exp(model.weights(BUILD["words"](s, d)).select(F.round("logw", 6).alias("logw"))).select(F.round("log_total", 4).alias("log_total"))
)
query("support_weights", f"{TX} SELECT tid, n, pow(2, n) - 1 AS w FROM t")(lambda s, d: sampler.support_weights(basket(s, d)).select("tid", F.col("n").cast("long").alias("n"), "w"))
query("length_law_basket", f"{TX} SELECT n, l, {CHOOSE.format('n - 1', 'l - 1')} AS ways FROM (SELECT DISTINCT n FROM t), range(1, 30) r(l) WHERE l <= n")(
    lambda s, d: length_law(s, [r.n for r in model.sizes(basket(s, d)).select("n").distinct().collect()], SUM).select(F.col("n").cast("long").alias("n"), F.col("l").cast("long").alias("l"), F.round((F.least("hi", F.lit(1.0)) - F.col("lo")) * F.pow(F.lit(2.0), F.col("n") - 1)).alias("ways"))
)
query("length_weights_basket", f"{TX} SELECT tid, l, round({CHOOSE.format('n - 1', 'l - 1')} * s, 2) AS mass FROM t, range(1, 30) r(l) WHERE l <= n")(
    lambda s, d: model.sizes(basket(s, d)).select("tid", "s", "n", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("l"))
    .select("tid", F.col("l").cast("long").alias("l"), F.round(F.expr("aggregate(sequence(0, l - 1), 1D, (a, k) -> if(k = 0, a, a * (n - k) / k))") * F.col("s"), 2).alias("mass"))
)


# --- triangle, binomials, matrix ----------------------------------------------------------------------------------

_PREFIX = f"WITH q AS ({QDB['basket']}), p AS (SELECT tid, row_number() OVER o AS i, item, w, CAST(sum(w) OVER o AS BIGINT) AS s FROM q WINDOW o AS (PARTITION BY tid ORDER BY item))"
_TRIANGLE = f"{_PREFIX} SELECT tid, l, i, round({CHOOSE.format('i - 1', 'l - 1')} * s) AS t FROM p, range(1, 30) r(l) WHERE l <= i"
_cell = lambda df: df.select("tid", F.col("l").cast("long").alias("l"), F.col("i").cast("long").alias("i"), F.round("t").alias("t"))
query("triangle_closed", _TRIANGLE)(lambda s, d: _cell(model.triangle(model.pack(basket(s, d)))))
query("triangle_recursive", _TRIANGLE)(lambda s, d: _cell(model.triangle_by_recursion(model.pack(basket(s, d)))))
query("triangle_symmetry", f"{_PREFIX} SELECT count(*) AS cells, CAST(0 AS BIGINT) AS odd FROM p, range(1, 30) r(l) WHERE l <= i")(lambda s, d: _symmetry(model.triangle(model.pack(basket(s, d)))))


def _symmetry(cells: DataFrame) -> DataFrame:
    mirror = cells.select("tid", "i", (F.col("i") - F.col("l") + 1).alias("l"), F.col("t").alias("t2"))
    return cells.join(mirror, ["tid", "i", "l"]).agg(F.count("*").alias("cells"), F.sum((F.col("t") != F.col("t2")).cast("long")).alias("odd"))


_SIZES = lambda name: f"SELECT DISTINCT n FROM (SELECT CAST(count(*) AS BIGINT) AS n FROM ({QDB[name]}) GROUP BY tid)"
_sizes_of = lambda s, d, name: model.sizes(BUILD[name](s, d)).select(F.col("n").cast("long").alias("n")).distinct()
query("pascal_cells", f"SELECT n, CAST(CASE WHEN n % 2 = 0 THEN (n // 2 + 1) * (n // 2 + 1) ELSE (n + 1) * (n + 3) // 4 END AS BIGINT) AS cells FROM ({_SIZES('shopper')})")(
    lambda s, d: s.createDataFrame([(r.n, pascal_cells(r.n)) for r in _sizes_of(s, d, "shopper").collect()], "n long, cells long")  # one row a size
)
query("binom_table", f"SELECT n, k, {CHOOSE.format('n', 'k')} AS c FROM ({_SIZES('basket')}), range(0, 31) b(k) WHERE k <= n")(
    lambda s, d: _sizes_of(s, d, "basket").select("n", F.explode(F.sequence(F.lit(0).cast("long"), "n")).alias("k")).select("n", "k", F.round(F.expr("aggregate(sequence(0L, k), 1D, (a, i) -> if(i = 0, a, a * (n - i + 1) / i))")).alias("c"))
)
query("matrix_weights_basket", _interval(1, 10).replace("SELECT tid, n, s, round", "SELECT tid, round").replace(", 4) AS w", ", 2) AS w"))(
    lambda s, d: matrix.matrix_weights(model.pack(basket(s, d)), 1, 10).select("tid", F.round("w", 2).alias("w"))
)
query("matrix_cells", f"{TX} SELECT CAST(sum(CASE WHEN n <= 10 THEN n * (n + 1) ELSE 110 + 20 * (n - 10) END) AS BIGINT) AS cells, false AS refused FROM t")(lambda s, d: matrix.cells(model.sizes(basket(s, d)), 10, whole=False))
query("matrix_refused", f"WITH q AS ({QDB['words']}), t AS (SELECT count(*) AS n FROM q GROUP BY tid) SELECT CAST(sum(n * (n + 1)) AS BIGINT) AS cells, sum(n * (n + 1)) > 50000000 AS refused FROM t")(lambda s, d: matrix.cells(model.sizes(BUILD["words"](s, d)), 1 << 20))
query("storage_model", f"{TX} SELECT count(*) AS weights, CAST(CASE WHEN max(n) % 2 = 0 THEN (max(n) // 2 + 1) * (max(n) // 2 + 1) ELSE (max(n) + 1) * (max(n) + 3) // 4 END AS BIGINT) AS cells, max(n) + 1 AS factors, CAST(sum(n * (n + 1)) AS BIGINT) AS matrix FROM t")(
    lambda s, d: metrics.storage_model(basket(s, d))
)


# --- enumeration and mining ---------------------------------------------------------------------------------------


def _occurrences(name: str, most: int) -> str:
    grow = f"SELECT o.tid, list_append(o.pattern, q.item), q.item, o.u + q.w, o.size + 1 FROM o JOIN q ON o.tid = q.tid AND q.item > o.last WHERE o.size < {most}"
    return f"WITH RECURSIVE q AS ({QDB[name]}), o AS (SELECT tid, [item] AS pattern, item AS last, w AS u, 1 AS size FROM q UNION ALL {grow}), e AS (SELECT pattern, sum(u) AS utility, count(*) AS support FROM o GROUP BY pattern)"


_PATTERN, _DUCK_KEY = "array_join(cast(pattern as array<string>), ',') AS pattern", "array_to_string(pattern, ',') AS pattern"
query("enumerate_visit", f"{_occurrences('visit', 5)} SELECT {_DUCK_KEY}, round(CAST(utility AS DOUBLE), 3) AS utility, support FROM e")(
    lambda s, d: mining.enumerate_patterns(encode.visit(s, d), 1, 5).select(F.expr(_PATTERN), F.round(F.col("utility").cast("double"), 3).alias("utility"), "support")
)
query("language_visit", f"{_occurrences('visit', 5)} SELECT {_DUCK_KEY}, len(pattern) >= 2 AND len(pattern) <= 3 AS inside FROM e")(
    lambda s, d: mining.enumerate_patterns(encode.visit(s, d), 1, 5).select(F.expr(_PATTERN), model.in_language(F.col("pattern"), 2, 3).alias("inside"))
)
query("enumerate_basket_pairs", f"{_occurrences('basket', 2)} SELECT {_DUCK_KEY}, CAST(utility AS BIGINT) AS utility, support FROM e")(
    lambda s, d: mining.enumerate_patterns(basket(s, d), 1, 2).select(F.expr(_PATTERN), "utility", "support")
)
query("target_distribution_visit", f"{_occurrences('visit', 5)} SELECT {_DUCK_KEY}, round(CAST(utility AS DOUBLE) / len(pattern) / (SELECT sum(CAST(utility AS DOUBLE) / len(pattern)) FROM e), 9) AS p FROM e")(
    lambda s, d: mining.target(encode.visit(s, d), LengthUtility("mean", 1, 5)).select(F.expr(_PATTERN), F.round("p", 9).alias("p"))
)
_ALL = 64  # longer than any basket: SQL enumerates every pattern
query("topk_sum", f"{_occurrences('basket', _ALL)} SELECT {_DUCK_KEY}, CAST(utility AS BIGINT) AS utility FROM e ORDER BY e.utility DESC, e.pattern LIMIT 20")(lambda s, d: mining.mine_topk(basket(s, d), 20, SUM).select(F.expr(_PATTERN), "utility"))
query("topk_mean", f"{_occurrences('basket', _ALL)} SELECT {_DUCK_KEY}, round(CAST(utility AS DOUBLE) / len(pattern), 4) AS value FROM e ORDER BY CAST(utility AS DOUBLE) / len(pattern) DESC, e.pattern LIMIT 20")(
    lambda s, d: mining.mine_topk(basket(s, d), 20, MEAN).select(F.expr(_PATTERN), F.round("value", 4).alias("value"))
)
query("threshold_mining", f"{_occurrences('basket', _ALL)} SELECT {_DUCK_KEY}, CAST(utility AS BIGINT) AS utility FROM e WHERE utility >= 30000000")(lambda s, d: mining.mine_threshold(basket(s, d), 30_000_000).select(F.expr(_PATTERN), "utility"))
_SUPER = "{0} SELECT {1} FROM e WHERE NOT EXISTS (SELECT 1 FROM e b WHERE len(b.pattern) > len(e.pattern) AND list_has_all(b.pattern, e.pattern){2})"
query("condensed_maximal", _SUPER.format(_occurrences("visit", 5), _DUCK_KEY, ""))(lambda s, d: mining.condense(mining.enumerate_patterns(encode.visit(s, d), 1, 5)).select(F.expr(_PATTERN)))
query("condensed_closed", _SUPER.format(_occurrences("visit", 5), _DUCK_KEY, " AND b.support = e.support"))(lambda s, d: mining.condense(mining.enumerate_patterns(encode.visit(s, d), 1, 5), "closed").select(F.expr(_PATTERN)))
query("mining_on_sample", _occurrences("basket", _ALL).replace(f"({QDB['basket']})", f"(SELECT * FROM ({QDB['basket']}) WHERE {duck_uniform('0', 'tid', chr(39) + 'sample' + chr(39))} < 0.5)", 1) + f" SELECT {_DUCK_KEY}, CAST(utility AS DOUBLE) / 0.5 AS utility, support FROM e WHERE utility >= 15000000")(
    lambda s, d: mining.mine_on_sample(basket(s, d), 0.5, 30_000_000).select(F.expr(_PATTERN), F.col("utility").cast("double").alias("utility"), "support")
)
query("mcmc_sample", None)(lambda s, d: mining.mcmc(encode.visit(s, d).withColumn("w", F.col("w").cast("double")), 16, 50, LengthUtility("const", 1, 3)))
_pairs = lambda s, d: basket(s, d).groupBy("tid").agg(F.slice(F.array_sort(F.collect_set("item")), 1, 2).alias("pattern")).select("pattern").distinct()
_PAIRS_SQL = f"WITH q AS ({QDB['basket']}), p AS (SELECT DISTINCT list_slice(list_sort(list(DISTINCT item)), 1, 2) AS pattern FROM q GROUP BY tid), x AS (SELECT pattern, unnest(pattern) AS item FROM p), m AS (SELECT pattern, tid, count(*) AS k, sum(w) AS u FROM x JOIN q USING (item) GROUP BY 1, 2)"
query("pattern_utility_pairs", f"{_PAIRS_SQL} SELECT {_DUCK_KEY}, CAST(coalesce(sum(u), 0) AS BIGINT) AS utility FROM m WHERE k = len(pattern) GROUP BY m.pattern")(lambda s, d: model.pattern_utility(basket(s, d), _pairs(s, d)).select(F.expr(_PATTERN), "utility"))
query("mean_utility_pairs", f"{_PAIRS_SQL} SELECT {_DUCK_KEY}, round(CAST(coalesce(sum(u), 0) AS DOUBLE) / len(m.pattern), 4) AS value FROM m WHERE k = len(pattern) GROUP BY m.pattern")(
    lambda s, d: model.pattern_utility(basket(s, d), _pairs(s, d)).select(F.expr(_PATTERN), F.round(F.col("utility") * model.length_factor(F.size("pattern"), MEAN), 4).alias("value"))
)
query("item_marginals", f"{TX}, z AS (SELECT sum(s * pow(2, n - 1)) AS z FROM t) SELECT item, round(sum(pow(2, n - 1) * w + CASE WHEN n > 1 THEN pow(2, n - 2) ELSE 0 END * (s - w)) / any_value(z), 9) AS p FROM q JOIN t USING (tid), z GROUP BY item")(
    lambda s, d: model.item_marginals(basket(s, d)).select("item", F.round("p", 9).alias("p"))
)


# --- draws, replayed in SQL ---------------------------------------------------------------------------------------


def _pick_sql(weight: str, name: str = "pk") -> str:
    x, y = duck_uniform(str(SEED), "draw_id", "'bucket'"), duck_uniform(str(SEED), "draw_id", "'tx'")
    return f"""v AS (SELECT tid, n, CAST({weight} AS DOUBLE) AS v, tid % 256 AS b FROM t), z AS (SELECT b, sum(v) AS z FROM v GROUP BY b),
      e AS (SELECT b, z, sum(z) OVER (ORDER BY b) AS e FROM z), d AS (SELECT range AS draw_id FROM range({K})),
      g AS (SELECT draw_id, (SELECT arg_min(b, e) FROM e WHERE e >= {x} * (SELECT max(e) FROM e)) AS b FROM d),
      y AS (SELECT draw_id, g.b, {y} * z AS y FROM g JOIN z ON g.b = z.b),
      r AS (SELECT tid, n, b, v, sum(v) OVER (PARTITION BY b ORDER BY tid) AS hi FROM v),
      {name} AS (SELECT draw_id, min(tid) AS tid, arg_min(n, tid) AS n FROM y JOIN r ON y.b = r.b AND y > hi - v AND y <= hi GROUP BY draw_id)"""


def _length_sql(top: str = "n") -> str:
    u = duck_uniform(str(SEED), "draw_id", "'length'")
    return f"""law AS (SELECT n, l, c, sum(c) OVER (PARTITION BY n ORDER BY l) AS hi, sum(c) OVER (PARTITION BY n) AS all_c FROM (SELECT n, l, {CHOOSE.format('n - 1', 'l - 1')} AS c FROM (SELECT DISTINCT n FROM t), range(1, 30) r(l) WHERE l <= {top})),
      dl AS (SELECT draw_id, tid, pk.n, min(l) AS l FROM pk JOIN law ON pk.n = law.n AND hi >= {u} * all_c GROUP BY 1, 2, 3)"""


_MASS = "(CASE WHEN {i} < {l} THEN 0.0 ELSE " + CHOOSE.format("({i} - 1)", "({l} - 1)") + " * s[{i}] + " + CHOOSE.format("{i}", "{l}") + " * {u} END)"
_ARRAYS = "a AS (SELECT tid, list(item ORDER BY item) AS items, list(CAST(w AS DOUBLE) ORDER BY item) AS w, list(CAST(s AS DOUBLE) ORDER BY item) AS s FROM (SELECT tid, item, w, sum(w) OVER (PARTITION BY tid ORDER BY item) AS s FROM q) GROUP BY tid)"


def _jump_sql(top: str = "n") -> str:
    # Masses without a choice by CASE: a filter over positions i >= rem needs none.
    mass = lambda i: f"({CHOOSE.format(f'({i} - 1)', '(rem - 1)')} * s[{i}] + (CASE WHEN {i} >= rem THEN {CHOOSE.format(i, 'rem')} ELSE 0 END) * u)"
    step = f"SELECT draw_id, tid, step + 1 AS step, rem, j, u, items, w, s, pat, list_filter(range(rem, j + 1), lambda i: {mass('i')} >= {duck_uniform(str(SEED), 'draw_id', 'step')} * {mass('j')})[1] AS i FROM st WHERE rem > 0"
    return f"""{TX.replace('WITH', 'WITH RECURSIVE', 1)}, {_pick_sql('s * pow(2, n - 1)' if top == 'n' else f's * c')}, {_length_sql(top)}, {_ARRAYS},
      st AS (SELECT draw_id, dl.tid, CAST(1 AS BIGINT) AS step, CAST(l AS BIGINT) AS rem, CAST(n AS BIGINT) AS j, CAST(0 AS DOUBLE) AS u, items, w, s, CAST([] AS BIGINT[]) AS pat FROM dl JOIN a ON dl.tid = a.tid
        UNION ALL SELECT draw_id, tid, step, rem - 1, i - 1, u + w[i], items, w, s, list_append(pat, items[i]) FROM ({step}))
      SELECT draw_id, tid, array_to_string(list_sort(pat), ',') AS pattern, len(pat) AS length FROM st WHERE rem = 0"""


def _picked(s: SparkSession, d: str, f: LengthUtility = SUM) -> DataFrame:
    return jump.draw_length(jump.pick_by_prefix(model.weights(basket(s, d), f), K, SEED), f, SEED)


_drawn = lambda df: df.select("draw_id", "tid", F.expr(_PATTERN), F.col("length").cast("long").alias("length"))
query("pick_tx_prefix", f"{TX}, {_pick_sql('s * pow(2, n - 1)')} SELECT draw_id, tid, n FROM pk")(lambda s, d: jump.pick_by_prefix(model.weights(basket(s, d)), K, SEED).select("draw_id", "tid", F.col("n").cast("long").alias("n")))
query("draw_length", f"{TX}, {_pick_sql('s * pow(2, n - 1)')}, {_length_sql()} SELECT draw_id, tid, n, l FROM dl")(lambda s, d: _picked(s, d).select("draw_id", "tid", F.col("n").cast("long").alias("n"), F.col("l").cast("long").alias("l")))
query("draw_jump_basket", _jump_sql())(lambda s, d: _drawn(sampler.sample(basket(s, d), K, seed=SEED, pick="prefix", engine="sql")))
query("draw_jump_arrow", _jump_sql())(lambda s, d: _drawn(sampler.sample(basket(s, d), K, seed=SEED, pick="prefix", engine="arrow")))
query("twopass_basket", _jump_sql())(lambda s, d: _drawn(sampler.two_pass(basket(s, d), K, seed=SEED)))


@query("twopass_stored_basket", _jump_sql())
def _(s: SparkSession, d: str) -> DataFrame:
    """The database laid out in buckets; the second pass reads those of the chosen transactions."""
    path = f"{shared_dir(s)}/qdb-{uuid.uuid4().hex}"
    tables.write_qdb(basket(s, d), path)
    return _drawn(sampler.two_pass_stored(path, s, K, seed=SEED))


def _log_sql(name: str, most: int, sequential: bool = False) -> str:
    """Draws of mean utility up to ``most`` items from long transactions, with logarithms of masses."""
    choose = lambda n, k: f"(lgamma({n} + 1) - lgamma({k} + 1) - lgamma({n} - {k} + 1))"
    mass = lambda i: f"({choose(i, 'rem')} + ln(rem * s[{i}] / {i} + u))"
    head = f"""WITH RECURSIVE q AS ({QDB[name]}), t AS (SELECT tid, count(*) AS n, CAST(sum(w) AS BIGINT) AS s FROM q GROUP BY tid),
      c AS (SELECT n, l, {choose('(n - 1)', '(l - 1)')} - ln(l) AS g FROM (SELECT DISTINCT n FROM t), range(1, {most + 1}) r(l) WHERE l <= n), m AS (SELECT n, max(g) AS top FROM c GROUP BY n),
      o AS (SELECT c.n, l, exp(g - top) AS c, top FROM c JOIN m ON c.n = m.n), k AS (SELECT n, any_value(top) + ln(sum(c)) AS logc FROM o GROUP BY n), y_ AS (SELECT tid, t.n, s, ln(s) + logc AS logw FROM t JOIN k ON t.n = k.n),
      {_pick_sql('exp(logw - (SELECT max(logw) FROM y_))').replace('FROM t)', 'FROM y_)', 1)},
      law AS (SELECT n, l, sum(c) OVER (PARTITION BY n ORDER BY l) AS hi, sum(c) OVER (PARTITION BY n) AS all_c FROM o),
      dl AS (SELECT draw_id, tid, pk.n, min(l) AS l FROM pk JOIN law ON pk.n = law.n AND hi >= {duck_uniform(str(SEED), 'draw_id', "'length'")} * all_c GROUP BY 1, 2, 3), {_ARRAYS}"""
    if sequential:
        u = duck_uniform(str(SEED), "draw_id", "i")
        stay = f"(i = rem OR ln({u}) + {mass('i')} > (CASE WHEN i > rem THEN {mass('greatest(i - 1, rem)')} ELSE 0 END))"
        return f"""{head}, st AS (SELECT draw_id, dl.tid, CAST(n AS BIGINT) AS i, CAST(l AS BIGINT) AS rem, CAST(0 AS DOUBLE) AS u, items, w, s, CAST([] AS BIGINT[]) AS pat FROM dl JOIN a ON dl.tid = a.tid
          UNION ALL SELECT draw_id, tid, i - 1, CASE WHEN hit THEN rem - 1 ELSE rem END, CASE WHEN hit THEN u + w[i] ELSE u END, items, w, s, CASE WHEN hit THEN list_append(pat, items[i]) ELSE pat END FROM (SELECT *, {stay} AS hit FROM st WHERE rem > 0))
          SELECT draw_id, tid, array_to_string(list_sort(pat), ',') AS pattern, len(pat) AS length FROM st WHERE rem = 0"""
    step = f"SELECT draw_id, tid, step + 1 AS step, rem, j, u, items, w, s, pat, list_filter(range(rem, j + 1), lambda i: {mass('i')} >= ln({duck_uniform(str(SEED), 'draw_id', 'step')}) + {mass('j')})[1] AS i FROM st WHERE rem > 0"
    return f"""{head}, st AS (SELECT draw_id, dl.tid, CAST(1 AS BIGINT) AS step, CAST(l AS BIGINT) AS rem, CAST(n AS BIGINT) AS j, CAST(0 AS DOUBLE) AS u, items, w, s, CAST([] AS BIGINT[]) AS pat FROM dl JOIN a ON dl.tid = a.tid
      UNION ALL SELECT draw_id, tid, step, rem - 1, i - 1, u + w[i], items, w, s, list_append(pat, items[i]) FROM ({step}))
      SELECT draw_id, tid, array_to_string(list_sort(pat), ',') AS pattern, len(pat) AS length FROM st WHERE rem = 0"""


for _name in ("supply", "shopper"):
    query(f"draw_jump_{_name}", _log_sql(_name, 10))(lambda s, d, build=BUILD[_name]: _drawn(sampler.sample(build(s, d), K, LengthUtility("mean", 1, 10), SEED, pick="prefix", engine="arrow")))
query("draw_sequential_supply", _log_sql("supply", 10, True))(lambda s, d: _drawn(sampler.sample(encode.supply(s, d), K, LengthUtility("mean", 1, 10), SEED, "sequential", pick="prefix", engine="arrow")))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _drawn(sampler.two_pass(basket(spark, sf_dir), 200, LengthUtility("mean", 1, 5), SEED))


def _sequential_sql(matrix: bool = False) -> str:
    mass = lambda i: f"(CASE WHEN {i} < rem THEN 0.0 ELSE {CHOOSE.format(f'greatest({i} - 1, rem - 1)', '(rem - 1)')} * s[greatest({i}, 1)] + {CHOOSE.format(f'greatest({i}, rem)', 'rem')} * u END)"
    stay = f"({duck_uniform(str(SEED), 'draw_id', 'i')} * {mass('i')} > {mass('(i - 1)')})"
    if matrix:
        u = duck_uniform(str(SEED), "draw_id", "'m'", "i")
        stay = f"({u} * {mass('i')} <= {mass('i')} - {mass('(i - 1)')})"
    return f"""{TX.replace('WITH', 'WITH RECURSIVE', 1)}, {_pick_sql('s * pow(2, n - 1)')}, {_length_sql()}, {_ARRAYS},
      st AS (SELECT draw_id, dl.tid, CAST(n AS BIGINT) AS i, CAST(l AS BIGINT) AS rem, CAST(0 AS DOUBLE) AS u, items, w, s, CAST([] AS BIGINT[]) AS pat, CAST(0 AS BIGINT) AS seen FROM dl JOIN a ON dl.tid = a.tid
        UNION ALL SELECT draw_id, tid, i - 1, CASE WHEN hit THEN rem - 1 ELSE rem END, CASE WHEN hit THEN u + w[i] ELSE u END, items, w, s, CASE WHEN hit THEN list_append(pat, items[i]) ELSE pat END, seen + 1
          FROM (SELECT *, {stay} AS hit FROM st WHERE rem > 0))
      SELECT draw_id, tid, array_to_string(list_sort(pat), ',') AS pattern, len(pat) AS length, seen AS visited FROM st WHERE rem = 0"""


def _with_packed(s: SparkSession, d: str) -> DataFrame:
    q, picks = basket(s, d), _picked(s, d)
    return picks.drop("n").join(model.pack(q), "tid")


query("draw_sequential_basket", _sequential_sql())(
    lambda s, d: (r := jump.sequential_in_sql(_with_packed(s, d), SEED)).select("draw_id", "tid", F.expr(_PATTERN), F.col("length").cast("long").alias("length"), F.col("visited").cast("long").alias("visited"))
)
query("draw_matrix_basket", _sequential_sql(True).replace(", seen AS visited", ""))(lambda s, d: _drawn(sampler.sample(basket(s, d), K, seed=SEED, method="matrix", pick="prefix")))
_SEED_SQL = f"""{TX}, {_pick_sql('s * pow(2, n - 1)')}, {_length_sql()},
  x AS (SELECT draw_id, dl.tid, l, item, -ln({duck_uniform(str(SEED), 'draw_id', 'item', "'seed'")}) / w AS race, {duck_uniform(str(SEED), 'draw_id', 'item', "'rest'")} AS u FROM dl JOIN q ON dl.tid = q.tid),
  f AS (SELECT draw_id, arg_min(item, race) AS first FROM x GROUP BY draw_id),
  k AS (SELECT x.draw_id, tid, l, item, row_number() OVER (PARTITION BY x.draw_id ORDER BY CASE WHEN item = first THEN -1.0 ELSE u END, item) AS rank FROM x JOIN f ON x.draw_id = f.draw_id)
  SELECT draw_id, tid, array_to_string(list(item ORDER BY item), ',') AS pattern, count(*) AS length FROM k WHERE rank <= l GROUP BY 1, 2"""
query("draw_seed_split_basket", _SEED_SQL)(lambda s, d: _drawn(jump.seed_split(_picked(s, d), basket(s, d), SEED)))


def _uniform_sql(share: str, weight: str = "1") -> str:
    return f"""{TX}, {_pick_sql(weight)}, law AS (SELECT n, l, sum(c) OVER (PARTITION BY n ORDER BY l) AS hi, sum(c) OVER (PARTITION BY n) AS all_c FROM (SELECT n, l, {share} AS c FROM (SELECT DISTINCT n FROM t), range(1, 6) r(l) WHERE l <= n)),
      dl AS (SELECT draw_id, tid, pk.n, min(l) AS l FROM pk JOIN law ON pk.n = law.n AND hi / all_c >= {duck_uniform(str(SEED), 'draw_id', "'length'")} GROUP BY 1, 2, 3),
      k AS (SELECT draw_id, dl.tid, l, item, row_number() OVER (PARTITION BY draw_id ORDER BY {duck_uniform(str(SEED), 'draw_id', 'item', "'subset'")}, item) AS rank FROM dl JOIN q ON dl.tid = q.tid)
      SELECT draw_id, tid, array_to_string(list(item ORDER BY item), ',') AS pattern, count(*) AS length FROM k WHERE rank <= l GROUP BY 1, 2"""


query("uniform_length_first", _uniform_sql("CAST(1 AS DOUBLE)"))(lambda s, d: _drawn(sampler.uniform_patterns(basket(s, d), K, 1, 5, "length_first", SEED)))
query("uniform_subset", _uniform_sql(CHOOSE.format("n", "l")))(lambda s, d: _drawn(sampler.uniform_patterns(basket(s, d), K, 1, 5, "subset_uniform", SEED)))
query("distinct_patterns", f"WITH drawn AS ({_jump_sql()}) SELECT pattern, count(*) AS times FROM drawn GROUP BY pattern")(
    lambda s, d: sampler.distinct_patterns(sampler.sample(basket(s, d), K, seed=SEED, pick="prefix", engine="sql")).select(F.expr(_PATTERN), "times")
)
query("str_pattern_key", f"WITH drawn AS ({_jump_sql()}) SELECT draw_id, md5(pattern) AS key FROM drawn")(
    lambda s, d: sampler.sample(basket(s, d), K, seed=SEED, pick="prefix", engine="sql").select("draw_id", F.md5(F.array_join(F.array_sort("pattern").cast("array<string>"), ",")).alias("key"))
)
_GUMBEL = duck_uniform(str(SEED), "draw_id", "tid", "'race'")
query("pick_tx_race", f"{TX}, x AS (SELECT range AS draw_id, tid, n, ln(s) + (n - 1) * ln(2) - ln(-ln({_GUMBEL})) AS key FROM t, range(20)) SELECT draw_id, arg_max(tid, key) AS tid, arg_max(n, key) AS n FROM x GROUP BY draw_id")(
    lambda s, d: jump.pick_by_race(model.weights(basket(s, d)), 20, SEED).select("draw_id", "tid", F.col("n").cast("long").alias("n"))
)
query("reservoir_sample", None)(lambda s, d: jump.pick_by_reservoir(model.weights(basket(s, d)), K, SEED))
query("draw_jump_words", None)(lambda s, d: sampler.sample(BUILD["words"](s, d), K, LengthUtility("mean", 1, 10), SEED, pick="prefix").select("draw_id", "tid", "pattern", "length"))
query("draw_jump_words_unbounded", None)(lambda s, d: sampler.sample(BUILD["words"](s, d), 200, SUM, SEED, pick="prefix").select("draw_id", "tid", "length"))
query("udf_exact_big_draw", None)(lambda s, d: _exact_draws(s, d))


def _exact_draws(s: SparkSession, d: str) -> DataFrame:
    """Whole-number draws from the suppliers' long transactions."""
    from gleaner.functions.chance import uniform_value

    def run(batches):
        import pyarrow as pa

        for b in batches:
            c = b.to_pydict()
            pats = [jump.draw_exact(it, w, k, lambda step, i=i: uniform_value(SEED, i, step)) for i, k, it, w in zip(c["draw_id"], c["l"], c["items"], c["w"], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("draw_id"), b.column("tid"), pa.array(pats, pa.list_(pa.int64()))], ["draw_id", "tid", "pattern"])

    q, f = encode.supply(s, d), LengthUtility("mean", 1, 5)
    picks = jump.draw_length(jump.pick_by_prefix(model.weights(q, f), 50, SEED), f, SEED)
    return picks.drop("n").join(model.pack(q), "tid").select("draw_id", "tid", "l", "items", "w").mapInArrow(run, "draw_id long, tid long, pattern array<long>")


# --- measures -----------------------------------------------------------------------------------------------------


def _graph(s: SparkSession, d: str, triples: Callable = encode.schema_triples) -> DataFrame:
    return written(kg.priced(kg.to_qdb(kg.simple_profile(triples(s, d)))), "graph")


def _two_samples(q: DataFrame) -> dict[str, DataFrame]:
    f = LengthUtility("mean", 1, 5)
    return {"jump": written(sampler.sample(q, K, f, SEED, pick="prefix"), "draws"), "uniform": written(sampler.uniform_patterns(q, K, 1, 5, "length_first", SEED), "draws")}


query("representativeness", None)(lambda s, d: metrics.representativeness(q := _graph(s, d), _two_samples(q)).groupBy("method").agg(F.count("*").alias("distinct"), F.max("times").alias("most"), F.avg("value").alias("mean_value")))
query("normalised_utility", None)(lambda s, d: metrics.normalised(metrics.representativeness(q := _graph(s, d), _two_samples(q))).select("method", "pattern", "times", "share"))
query("ci_summary", None)(lambda s, d: metrics.spread(metrics.normalised(metrics.representativeness(q := _graph(s, d), _two_samples(q)))))
query("fit_graph_marginals", None)(lambda s, d: metrics.marginals(sampler.sample(q := _graph(s, d), K, SUM, SEED, pick="prefix"), model.item_marginals(q)))
_FIT_SQL = f"""WITH drawn AS ({_jump_sql("least(n, 2)").replace("s * c AS DOUBLE", "s * n AS DOUBLE")}), c AS (SELECT pattern, count(*) AS times FROM drawn GROUP BY pattern),
  law AS ({_occurrences("basket", 2)} SELECT {_DUCK_KEY}, CAST(utility AS DOUBLE) / (SELECT sum(CAST(utility AS DOUBLE)) FROM e) AS p FROM e),
  b AS (SELECT coalesce(p, 0) AS p, coalesce(times, 0) / {K} AS q FROM law FULL JOIN c USING (pattern))
  SELECT CAST({K} AS BIGINT) AS k, count(*) AS patterns, round(sum(abs(q - p)) / 2, 6) AS tv, round(max(abs(q - p)), 6) AS max_error,
    round(sum(CASE WHEN q > 0 THEN q * ln(q / p) END), 6) AS kl, round({K} * sum((q - p) * (q - p) / p), 4) AS chi2 FROM b"""
query("fit_basket", _FIT_SQL)(
    lambda s, d: metrics.fit(sampler.sample(q := basket(s, d), K, f := LengthUtility("const", 1, 2), SEED, pick="prefix"), mining.target(q, f))
    .select("k", "patterns", *[F.round(c, 4 if c == "chi2" else 6).alias(c) for c in ("tv", "max_error", "kl", "chi2")])
)
query("diversity", f"WITH drawn AS ({_jump_sql()}), c AS (SELECT pattern, count(*) AS t FROM drawn GROUP BY pattern) SELECT CAST(sum(t) AS BIGINT) AS k, count(*) AS distinct, round(ln(sum(t)) - sum(t * ln(t)) / sum(t), 6) AS entropy FROM c".replace(" AS distinct", ' AS "distinct"'))(
    lambda s, d: metrics.diversity(sampler.sample(basket(s, d), K, seed=SEED, pick="prefix", engine="sql")).select("k", "distinct", F.round("entropy", 6).alias("entropy"))
)
query("mean_jaccard", f"WITH drawn AS ({_jump_sql()}), l AS (SELECT draw_id, string_split(pattern, ',') AS p FROM drawn), m AS (SELECT len(list_intersect(a.p, b.p)) AS i, len(a.p) + len(b.p) AS n FROM l a JOIN l b ON b.draw_id = a.draw_id + 1) SELECT count(*) AS pairs, round(avg(i / (n - i)), 6) AS jaccard FROM m")(
    lambda s, d: metrics.mean_jaccard(sampler.sample(basket(s, d), K, seed=SEED, pick="prefix")).select("pairs", F.round("jaccard", 6).alias("jaccard"))
)


@query("draw_costs", None)
def _(s: SparkSession, d: str) -> DataFrame:
    """Uniforms and looks at masses that each method needs for the same picks: one uniform an item and a search, or one a visit."""
    q = written(encode.supply(s, d), "qdb")
    one = sampler.Sampler(q, LengthUtility("mean", 1, 10), SEED)
    rows = jump.grouped(one.picks(K, "prefix"), model.pack(q), "items", "w", "s")
    by = lambda name, df, uniforms: df.agg(F.lit(name).alias("method"), F.count("*").alias("draws"), F.sum(uniforms).alias("uniforms"), F.sum("visited").alias("looks"))
    return by("jump", jump.jump_in_arrow(rows, SEED), "length").unionByName(by("sequential", jump.sequential_in_arrow(rows, SEED), "visited"))


#: Subsets of 1 to 5 of n items, which a shorter transaction has fewer sizes of.
_SUBSETS = " + ".join("n" + "".join(f" * (n - {i})" for i in range(1, x)) + f" / {factorial(x)}" for x in range(1, 6))
query("draw_support_basket", _uniform_sql(CHOOSE.format("n", "l"), _SUBSETS))(lambda s, d: _drawn(sampler.support_sample(basket(s, d), K, 1, 5, SEED)))
for _name, _triples in (("schema", encode.schema_triples), ("links", encode.link_triples)):
    query(f"violin_{_name}", None)(lambda s, d, triples=_triples: metrics.violin(metrics.normalised(metrics.representativeness(q := _graph(s, d, triples), _two_samples(q)))))
query("spread_links", None)(lambda s, d: metrics.spread(metrics.normalised(metrics.representativeness(q := _graph(s, d, encode.link_triples), _two_samples(q)))))


# --- knowledge graphs ---------------------------------------------------------------------------------------------

_SIMPLE = lambda s, d: kg.simple_profile(encode.schema_triples(s, d))
for _way, _end in (("out", "subj"), ("in", "obj")):
    query(f"graph_qdb_{_way}", f"WITH t AS ({SCHEMA_TRIPLES}) SELECT '{_way}|' || {_end} AS tid, count(*) AS n, CAST(sum(weight) AS BIGINT) AS s FROM t GROUP BY 1")(
        lambda s, d, way=_way: kg.to_qdb(_SIMPLE(s, d), way).groupBy("tid").agg(F.count("*").alias("n"), F.sum("qty").alias("s"))
    )
query("graph_weights", f"WITH q AS ({QDB['graph']}) SELECT tid, count(*) AS n, round(ln(sum(w)) + (count(*) - 1) * ln(2), 6) AS logw FROM q GROUP BY tid")(
    lambda s, d: model.weights(BUILD["graph"](s, d)).select("tid", F.col("n").cast("long").alias("n"), F.round("logw", 6).alias("logw"))
)
query("graph_stats", f"WITH t AS ({SCHEMA_TRIPLES}), n AS (SELECT subj AS x FROM t UNION SELECT obj FROM t) SELECT (SELECT count(*) FROM t) AS triples, (SELECT count(*) FROM (SELECT DISTINCT subj, obj FROM t)) AS links, (SELECT count(*) FROM n) AS nodes")(lambda s, d: kg.stats(_SIMPLE(s, d)))


def _sub(s: SparkSession, d: str, k: int = 10, triples: Callable = encode.schema_triples) -> tuple[DataFrame, DataFrame, DataFrame]:
    profile = written(kg.simple_profile(triples(s, d)), "profile")
    q = written(kg.priced(kg.to_qdb(profile)), "graph")
    drawn = written(sampler.sample(q, k, LengthUtility("mean", 1, 5), SEED, pick="prefix").withColumn("all", F.lit(0)), "draws")
    return drawn, *kg.sub_profile(drawn, profile, "all")


_PRED = "SELECT 'contains' AS pred, CAST(2 AS BIGINT) AS price UNION ALL SELECT 'partOf', 5"
query("graph_predicate_weights", f"WITH t AS ({SCHEMA_TRIPLES}), p AS ({_PRED}), x AS (SELECT 'out|' || subj AS tid, weight * coalesce(price, 1) AS w FROM t LEFT JOIN p ON t.pred = p.pred UNION ALL SELECT 'in|' || obj, weight * coalesce(price, 1) FROM t LEFT JOIN p ON t.pred = p.pred) SELECT tid, count(*) AS n, CAST(sum(w) AS BIGINT) AS s FROM x GROUP BY tid")(
    lambda s, d: model.sizes(kg.priced(kg.to_qdb(_SIMPLE(s, d)), s.sql(_PRED))).select("tid", F.col("n").cast("long").alias("n"), "s")
)
query("graph_reweighted", f"WITH t AS ({SCHEMA_TRIPLES}), p AS ({_PRED}), x AS (SELECT 'out|' || subj AS tid, weight * coalesce(price, 1) AS w FROM t LEFT JOIN p ON t.pred = p.pred UNION ALL SELECT 'in|' || obj, weight * coalesce(price, 1) FROM t LEFT JOIN p ON t.pred = p.pred) SELECT tid, round(ln(sum(w)) + (count(*) - 1) * ln(2), 6) AS logw FROM x GROUP BY tid")(
    lambda s, d: sampler.Sampler(kg.priced(kg.to_qdb(_SIMPLE(s, d)), s.sql("SELECT 'contains' AS pred, 7L AS price")), SUM, SEED).reweight(s.sql(_PRED), key="pred").weights.select("tid", F.round("logw", 6).alias("logw"))
)
_CLASSES = "SELECT 'c' || c_custkey AS node, unnest(['Customer', c_mktsegment, 'N' || c_nationkey]) AS type FROM customer UNION ALL SELECT 'o' || o_orderkey, unnest(['Order', o_orderpriority]) FROM orders"
query("profile_built", f"WITH y AS ({_CLASSES}), k AS (SELECT node, array_to_string(list_sort(list(DISTINCT type)), ',') AS labels FROM y GROUP BY node) SELECT a.labels AS subj, 'places' AS pred, b.labels AS obj, count(*) AS weight FROM orders JOIN k a ON a.node = 'c' || o_custkey JOIN k b ON b.node = 'o' || o_orderkey GROUP BY 1, 3")(
    lambda s, d: _built(s, d).select(F.array_join("subj", ",").alias("subj"), "pred", F.array_join("obj", ",").alias("obj"), "weight")
)
query("profile_merged_nodes", f"WITH y AS ({_CLASSES}), b AS (SELECT type, node, left(node, 1) AS side FROM y WHERE node IN (SELECT 'c' || o_custkey FROM orders) OR left(node, 1) = 'o'), m AS (SELECT side, min(type) AS node FROM b GROUP BY side) SELECT DISTINCT b.type AS label, m.node FROM b JOIN m ON b.side = m.side")(
    lambda s, d: kg.merge_nodes(_built(s, d))
)
query("profile_merged_weights", "SELECT p || '|' || k AS tid, count(*) AS n, CAST(sum(w) AS BIGINT) AS s FROM (SELECT c, o, count(*) AS w FROM (SELECT concat(c_mktsegment, c_nationkey) AS c, o_orderpriority AS o FROM orders JOIN customer ON o_custkey = c_custkey) GROUP BY 1, 2), (SELECT 'out' AS p, (SELECT least(min(c_mktsegment), 'Customer', min('N' || c_nationkey)) FROM orders JOIN customer ON o_custkey = c_custkey) AS k UNION ALL SELECT 'in', (SELECT least(min(o_orderpriority), 'Order') FROM orders)) GROUP BY 1")(
    lambda s, d: model.sizes(kg.priced(kg.to_qdb(_built(s, d)))).select("tid", F.col("n").cast("long").alias("n"), "s")
)


def _built(s: SparkSession, d: str) -> DataFrame:
    """A profile built from instances with several classes each: who places which orders."""
    orders, customers = tables.load(s, d, "orders", "o_orderkey", "o_custkey", "o_orderpriority"), tables.load(s, d, "customer", "c_custkey", "c_mktsegment", "c_nationkey")
    name = lambda kind, column: F.concat(F.lit(kind), F.col(column).cast("string"))
    triples = orders.select(name("c", "o_custkey").alias("s"), F.lit("places").alias("p"), name("o", "o_orderkey").alias("o"))
    types = customers.select(name("c", "c_custkey").alias("node"), F.explode(F.array(F.lit("Customer"), "c_mktsegment", name("N", "c_nationkey"))).alias("type"))
    types = types.unionByName(orders.select(name("o", "o_orderkey").alias("node"), F.explode(F.array(F.lit("Order"), "o_orderpriority")).alias("type")))
    return written(kg.build_profile(triples, types), "profile")


query("sub_profile_top_nodes", None)(lambda s, d: kg.top_nodes(_sub(s, d)[2]))
query("sub_profile_links", None)(lambda s, d: kg.shape(*_sub(s, d, triples=encode.link_triples)[1:]))
query("sub_profile_nodes", None)(lambda s, d: _sub(s, d)[1].select(F.array_join("labels", ",").alias("labels")))
query("sub_profile_edges", None)(lambda s, d: _sub(s, d)[2].select("src", "pred", "dst", "weight"))
query("sub_profile_isolated", "SELECT CAST(0 AS BIGINT) AS isolated")(lambda s, d: kg.isolated(*_sub(s, d)[1:]).agg(F.count("*").alias("isolated")))
query("sub_profile_shape", None)(lambda s, d: kg.shape(*_sub(s, d)[1:]))
query("sub_profile_json", None)(lambda s, d: kg.export(*_sub(s, d)[1:]))
query("sub_profile_dot", None)(lambda s, d: kg.export(*_sub(s, d)[1:], how="dot"))


# --- measured experiments: few repeats here, more in bench.py ------------------------------------------------------

_few = lambda s, d: {"basket": basket(s, d), "supply": encode.supply(s, d), "census": encode.census(s, d)}
query("exp_sweep", None)(lambda s, d: experiments.sweep({"basket": basket(s, d)}, (5, None), K, 1))
query("exp_speed_up", None)(lambda s, d: experiments.speed_up(experiments.sweep({"basket": basket(s, d)}, (10,), K, 1, ("jump", "matrix"))))
query("exp_triangle_ways", None)(lambda s, d: experiments.recursion_against_closed(basket(s, d), 1))
query("exp_sizes", None)(lambda s, d: experiments.sizes_on_disk(_few(s, d)))


@query("exp_response", None)
def _(s: SparkSession, d: str) -> DataFrame:
    """(patterns, seconds): from new predicate prices to a sub-profile, the graph's database being there."""
    profile = written(_SIMPLE(s, d), "profile")
    one = sampler.Sampler(written(kg.priced(kg.to_qdb(profile)), "graph"), LengthUtility("mean", 1, 5), SEED)

    def draw() -> tuple[DataFrame, DataFrame]:
        drawn = one.reweight(s.sql(_PRED), key="pred").sample(10, pick="prefix").withColumn("all", F.lit(0))
        return kg.sub_profile(written(drawn, "draws"), profile, "all")

    return s.createDataFrame([(10, experiments.response(draw, 1)[0])], "patterns int, seconds double")


# --- forms of the worked example, on the given tables -------------------------------------------------------------

_KINDS = "SELECT user_id AS tid, event_type AS item, count(*) AS w FROM events GROUP BY 1, 2"


def _kinds(s: SparkSession, d: str) -> DataFrame:
    """Users by kind of event, counted."""
    return tables.load(s, d, "events", "user_id", "event_type").groupBy(F.col("user_id").alias("tid"), F.col("event_type").alias("item")).agg(F.count("*").alias("w"))


query("toy_weights", f"WITH q AS ({_KINDS}) SELECT tid, CAST(sum(w) * pow(2, count(*) - 1) AS DOUBLE) AS w FROM q GROUP BY tid")(lambda s, d: model.weights(_kinds(s, d)).select("tid", F.round("w", 6).alias("w")))
query("toy_patterns", _occurrences("visit", _ALL).replace(QDB["visit"], _KINDS, 1) + f" SELECT {_DUCK_KEY}, CAST(utility AS BIGINT) AS utility FROM e")(
    lambda s, d: mining.enumerate_patterns(q := _kinds(s, d), 1, model.sizes(q).agg(F.max("n")).first()[0] or 1).select(F.expr(_PATTERN), "utility")
)
query("toy_graph", _sql["profile_merged_weights"].replace("count(*) AS n, CAST(sum(w) AS BIGINT) AS s", "w AS qty, 'places' AS pred", 1).removesuffix(" GROUP BY 1"))(lambda s, d: kg.to_qdb(_built(s, d)).select("tid", "qty", "pred"))
query("coefficients", f"SELECT n, CAST(pow(2, n - 1) AS DOUBLE) AS c FROM ({_SIZES('shopper')})")(
    lambda s, d: coefficients(s, [r.n for r in _sizes_of(s, d, "shopper").collect()], SUM).select(F.col("n").cast("long").alias("n"), "c")  # one row a size
)
