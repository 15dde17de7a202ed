"""Quantitative databases: (tid, item, w) rows, their transactions and the utility of patterns."""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gleaner.operators.lengths import SUM, LengthUtility, coefficient, coefficients, log_of
from gleaner.sources.shared import written


def weigh(qdb: DataFrame, prices: DataFrame | None = None, key: str = "item", default: float = 1) -> DataFrame:
    """(tid, item, w = qty * price); ``prices``: (key, price), where ``key`` is a column of ``qdb`` such as item or pred."""
    if prices is None:
        return qdb.select("tid", "item", (F.col("qty") * F.lit(default)).alias("w"))
    priced = qdb.join(prices.select(F.col(prices.columns[0]).alias(key), F.col(prices.columns[1]).alias("price")), key, "left")
    return priced.select("tid", "item", (F.col("qty") * F.coalesce("price", F.lit(default))).alias("w"))


def validate(qdb: DataFrame) -> DataFrame:
    """Weights of repeated (tid, item) are summed; null keys and weights that are null or not positive are left out."""
    good = qdb.where("tid is not null and item is not null and w > 0")
    return good.groupBy("tid", "item").agg(F.sum("w").alias("w"))


def restrict(qdb: DataFrame, allow: DataFrame | None = None, deny: DataFrame | None = None) -> DataFrame:
    """Patterns that avoid items follow the same law on the database without them."""
    qdb = qdb.join(allow.select("item"), "item", "left_semi") if allow is not None else qdb
    return qdb.join(deny.select("item"), "item", "left_anti") if deny is not None else qdb


def sizes(qdb: DataFrame) -> DataFrame:
    """(tid, n, s): one pass, combined before the shuffle."""
    return qdb.groupBy("tid").agg(F.count("*").cast("int").alias("n"), F.sum("w").alias("s"))


def weights(qdb: DataFrame, f: LengthUtility = SUM, per: DataFrame | None = None) -> DataFrame:
    """(tid, n, s, w, logw): total utility of each transaction's patterns. ``w`` is null where a double can't hold it.

    Transactions without a pattern in the interval drop out. Closed forms are column expressions over one scan of
    ``qdb``; else the sizes are written once, and their coefficients, one row per distinct size, joined. ``per``: sizes known.
    """
    n, log_s = F.col("n"), F.ln(F.col("s").cast("double"))
    if f.closed:
        log2 = math.log(2)
        logc = (n - 1) * log2 if f.kind == "const" else n * log2 + F.log1p(-F.pow(F.lit(2.0), -n)) - F.ln(n)
        c = F.pow(F.lit(2.0), n - 1) if f.kind == "const" else (F.pow(F.lit(2.0), n) - 1) / n
        return (sizes(qdb) if per is None else per).select("tid", "n", "s", F.when(logc < 700, F.col("s") * c).alias("w"), (log_s + logc).alias("logw"))
    per = written(sizes(qdb), "sizes") if per is None else per
    coef = coefficients(qdb.sparkSession, known_sizes(per), f)
    return per.join(F.broadcast(coef), "n").select("tid", "n", "s", (F.col("s") * F.col("c")).alias("w"), (log_s + F.col("logc")).alias("logw"))


def known_sizes(per: DataFrame) -> list[int]:
    """The distinct sizes of transactions, ascending: as many as the longest transaction has items at most."""
    return sorted(r.n for r in per.select("n").distinct().collect())


def log_sum_exp(df: DataFrame, column: str = "logw") -> DataFrame:
    """(top, log_total) of a column of logarithms, by two combined aggregates."""
    top = df.agg(F.max(column).alias("top"))
    return df.crossJoin(F.broadcast(top)).groupBy("top").agg((F.first("top") + F.ln(F.sum(F.exp(F.col(column) - F.col("top"))))).alias("log_total"))  # top: one row


def pack(qdb: DataFrame) -> DataFrame:
    """(tid, items, w, s, n): arrays in item order; s holds prefix sums. For picked transactions.

    Prefix sums are a running window before the arrays are collected, so their cost is that of a sort.
    """
    run = F.sum(F.col("w").cast("double")).over(Window.partitionBy("tid").orderBy("item").rowsBetween(Window.unboundedPreceding, 0))
    rows = qdb.select("tid", "item", "w").withColumn("s", run).groupBy("tid").agg(F.array_sort(F.collect_list(F.struct("item", "w", "s"))).alias("r"))
    rows = rows.select("tid", F.expr("transform(r, x -> x.item)").alias("items"), F.expr("transform(r, x -> cast(x.w as double))").alias("w"), F.expr("transform(r, x -> x.s)").alias("s"))
    return rows.withColumn("n", F.size("items"))


def utility_in_tx(qdb: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern, tid, utility) where a transaction holds the whole pattern; ``patterns``: (pattern array)."""
    items = patterns.select("pattern", F.explode(F.array_distinct("pattern")).alias("item"))
    met = items.join(qdb, "item").groupBy("pattern", "tid").agg(F.count("*").alias("k"), F.sum("w").alias("utility"))
    return met.where(F.col("k") == F.size(F.array_distinct("pattern"))).select("pattern", "tid", "utility")


def pattern_utility(qdb: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern, utility) over the whole database; 0 where it stands nowhere."""
    total = utility_in_tx(qdb, patterns).groupBy("pattern").agg(F.sum("utility").alias("utility"))
    return patterns.select("pattern").distinct().join(total, "pattern", "left").select("pattern", F.coalesce("utility", F.lit(0)).alias("utility"))


def length_factor(length: Column, f: LengthUtility) -> Column:
    """f as a column expression, for every length."""
    x = length.cast("double")
    if f.kind == "table":
        table = F.create_map(*[F.lit(v) for k, y in f.table for v in (int(k), float(y))]) if f.table else F.create_map()
        value: Column = F.coalesce(table[length.cast("int")], F.lit(0.0))
    else:
        value = {"const": F.lit(1.0), "mean": 1 / x, "power": F.pow(x, F.lit(-f.a)), "decay": F.exp(-f.a * x)}[f.kind]
    inside = length >= max(f.m, 1)
    return F.when(inside & (length <= f.M) if f.M is not None else inside, value).otherwise(0.0)


def in_language(pattern: Column, m: int = 1, M: int | None = None) -> Column:  # noqa: N803
    inside = F.size(pattern) >= max(m, 1)
    return inside & (F.size(pattern) <= M) if M is not None else inside


def triangle(packed: DataFrame) -> DataFrame:
    """(tid, l, i, t) for l <= i: summed utility of the l-subsets of the first i items, in closed form. An audit: n * n rows."""
    cells = packed.select("tid", "s", F.posexplode("s").alias("p", "prefix")).select("tid", "prefix", (F.col("p") + 1).alias("i"))
    cells = cells.select("tid", "i", "prefix", F.explode(F.sequence(F.lit(1), F.col("i"))).alias("l"))
    binom = F.expr("aggregate(sequence(0, l - 1), 1D, (a, k) -> if(k = 0, a, a * (i - k) / k))")
    return cells.select("tid", "l", "i", F.round(binom * F.col("prefix")).alias("t"))


def triangle_by_recursion(packed: DataFrame) -> DataFrame:
    """The same cells from their neighbours: each column, and each row of binomials, follows from the one before."""
    start = "named_struct('cols', cast(array() as array<array<double>>), 'row', cast(array() as array<double>))"
    row = "transform(sequence(0, i - 1), k -> if(k = 0 or k = i - 1, 1D, get(st.row, k - 1) + get(st.row, k)))"
    cell = "if(l = 1, get(s, i - 1), get(row, l - 1) * get(w, i - 1) + coalesce(get(get(st.cols, i - 2), l - 2), 0D) + coalesce(get(get(st.cols, i - 2), l - 1), 0D))"
    step = f"get(transform(array({row}), row -> named_struct('cols', concat(st.cols, array(transform(sequence(1, i), l -> {cell}))), 'row', row)), 0)"
    cols = packed.select("tid", F.posexplode(F.expr(f"aggregate(sequence(1, n), {start}, (st, i) -> {step}).cols")).alias("p", "col"))
    return cols.select("tid", (F.col("p") + 1).alias("i"), F.posexplode("col").alias("q", "t")).select("tid", (F.col("q") + 1).alias("l"), "i", "t")


def item_marginals(qdb: DataFrame, f: LengthUtility = SUM) -> DataFrame:
    """(item, p): how often each item stands in a drawn pattern, without enumerating: each length's share in closed form.

    Masses are relative to the largest coefficient, so that transactions of any length are held by doubles.
    """
    per = written(sizes(qdb), "sizes")
    # An l-subset holds x with mass C(n-1,l-1) w_x + C(n-2,l-2) (S - w_x); summed over lengths, two numbers per size.
    rows = []
    for n in known_sizes(per):
        top = n if f.M is None else min(f.M, n)
        own = coefficient(n, f)
        others = sum((math.comb(n - 2, x - 2) * f(x) for x in range(max(f.m, 2), top + 1)), Fraction(0))
        if own:
            rows.append((n, log_of(own), log_of(others) if others else None))
    most = max((r[1] for r in rows), default=0.0)
    scaled = [(n, math.exp(own - most), 0.0 if others is None else math.exp(others - most)) for n, own, others in rows]
    both = F.broadcast(qdb.sparkSession.createDataFrame(scaled, "n int, own double, others double"))  # one row a size
    known = per.join(both, "n")
    mass = qdb.join(known, "tid").select("item", (F.col("own") * F.col("w") + F.col("others") * (F.col("s") - F.col("w"))).alias("mass"))
    z = known.agg(F.sum(F.col("s") * F.col("own")).alias("z"))
    return mass.groupBy("item").agg(F.sum("mass").alias("mass")).crossJoin(F.broadcast(z)).select("item", (F.col("mass") / F.col("z")).alias("p"))  # z: one row
