"""Drawing patterns: transactions, lengths, then items from the right end to the left."""

from __future__ import annotations

import bisect
import math
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gleaner.functions.chance import uniform
from gleaner.operators.lengths import LengthUtility, length_law
from gleaner.operators.model import known_sizes
from gleaner.sources.shared import written

#: Least and most buckets (stretches of buckets), transactions a stretch is meant to have, longest transaction for nested expressions, draws sent with one copy of a transaction.
BUCKETS, MOST_BUCKETS, PER_BUCKET, SQL_MOST, TOGETHER = 256, 1 << 20, 4096, 60, 64


# --- transactions -------------------------------------------------------------------------------------------------


def _bucket(weights: DataFrame, buckets: int) -> Column:
    whole = dict(weights.dtypes)["tid"] in ("bigint", "int", "smallint", "tinyint")
    return F.pmod(F.col("tid").cast("long") if whole else F.xxhash64("tid"), F.lit(buckets)).cast("int")


def pick_by_prefix(weights: DataFrame, k: int, seed: int = 0, buckets: int | None = None) -> DataFrame:
    """(draw_id, tid, n): k transactions in proportion to weight, with replacement, by two searches in running totals.

    Whole-number ids always fall into as many buckets, so that a seed draws the same from any engine; a bucket is cut into
    stretches of ids, which grow in number with the transactions, so each stays small. (Other ids have no stretches: their buckets
    grow in number.) Totals of stretches come to the driver (one number each, ``MOST_BUCKETS`` at most); draws find bucket and
    stretch by binary search there, and are then sorted in among the running totals of the stretches hit, where each takes
    the transaction that follows it: no draw meets more than one row.
    """
    spark = weights.sparkSession
    kind = dict(weights.dtypes)["tid"]
    whole = kind in ("bigint", "int", "smallint", "tinyint")
    ends_of_ids = [F.min("tid").cast("long"), F.max("tid").cast("long")] if whole else [F.lit(0), F.lit(0)]
    top, rows_in, least, most = weights.agg(F.max("logw"), F.count("*"), *ends_of_ids).first()
    if top is None or k <= 0:
        return spark.createDataFrame([], f"draw_id long, tid {kind}, n int")
    buckets = buckets or (BUCKETS if whole else min(MOST_BUCKETS, max(BUCKETS, rows_in // PER_BUCKET)))
    parts = max(1, min(MOST_BUCKETS // buckets, rows_in // (buckets * PER_BUCKET))) if whole else 1
    part = F.floor((F.col("tid").cast("decimal(20,0)") - least) / ((most - least) // parts + 1)).cast("int") if parts > 1 else F.lit(0)
    exact = F.coalesce(F.col("w").cast("double"), F.lit(0.0)) if top < 36 else F.exp(F.col("logw") - top)
    rows = weights.select("tid", "n", exact.alias("v"), _bucket(weights, buckets).alias("bucket"), part.alias("part"))
    totals = sorted(((r.bucket, r.part), r.z) for r in rows.groupBy("bucket", "part").agg(F.sum("v").alias("z")).collect() if r.z > 0)
    of, part_ids, sums = (np.array(x) for x in ([t[0][0] for t in totals], [t[0][1] for t in totals], [t[1] for t in totals]))
    ids, first = np.unique(of, return_index=True)
    last = np.append(first[1:], len(of))
    runs = np.concatenate([np.cumsum(sums[i:j]) for i, j in zip(first, last, strict=True)])  # within each bucket
    zs = runs[last - 1]
    ends = np.cumsum(zs)
    draws = spark.range(k).select(F.col("id").alias("draw_id"), (uniform(seed, F.col("id"), "bucket") * float(ends[-1])).alias("x"), uniform(seed, F.col("id"), "tx").alias("y"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = np.minimum(np.searchsorted(ends, batch.column("x").to_numpy()), len(ends) - 1)
            y = batch.column("y").to_numpy() * zs[at]
            found = np.array([min(i + int(np.searchsorted(runs[i:j], v)), j - 1) for i, j, v in zip(first[at], last[at], y, strict=True)], dtype=np.int64)
            before = np.where(found > first[at], runs[found - 1], 0.0)
            yield pa.RecordBatch.from_arrays([batch.column("draw_id"), pa.array(ids[at], pa.int32()), pa.array(part_ids[found], pa.int32()), pa.array(before, pa.float64()), pa.array(y, pa.float64())], ["draw_id", "bucket", "part", "before", "y"])

    draws = draws.mapInArrow(place, "draw_id long, bucket int, part int, before double, y double")
    hit = rows.join(F.broadcast(draws.select("bucket", "part", "before").distinct()), ["bucket", "part"])  # at most one row a draw
    in_order = Window.partitionBy("bucket", "part").orderBy("tid")
    run = F.col("before") + F.sum("v").over(in_order.rowsBetween(Window.unboundedPreceding, 0))
    end = F.when(F.lead("tid").over(in_order).isNull(), F.lit(math.inf)).otherwise(run)
    spans = hit.select("bucket", "part", end.alias("at"), F.struct("tid", "n").alias("t"), F.lit(None).cast("long").alias("draw_id"), "tid")
    points = draws.select("bucket", "part", F.col("y").alias("at"), F.lit(None).cast(spans.schema["t"].dataType).alias("t"), "draw_id", F.lit(None).cast(kind).alias("tid"))
    # From the largest total down, the last transaction met before a draw is the first whose total reaches it.
    down = Window.partitionBy("bucket", "part").orderBy(F.desc("at"), F.desc_nulls_last("tid")).rowsBetween(Window.unboundedPreceding, 0)
    merged = spans.unionByName(points).withColumn("t", F.last("t", ignorenulls=True).over(down))
    return merged.where("draw_id is not null").select("draw_id", "t.tid", "t.n")


def pick_by_race(weights: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """The same law for few draws: every transaction runs in every draw, the largest log weight plus Gumbel noise wins."""
    draws = F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("draw_id")
    key = F.col("logw") - F.ln(-F.ln(uniform(seed, F.col("draw_id"), F.col("tid"), "race")))
    return weights.select("tid", "n", "logw", draws).groupBy("draw_id").agg(F.max_by(F.struct("tid", "n"), key).alias("t")).select(F.col("draw_id").cast("long"), "t.tid", "t.n")


def pick_by_reservoir(weights: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """The same law in one pass: each partition keeps k winners and its total, and winners of partitions meet again.

    Rows are dealt and sorted by tid first, so that a task that runs again throws the same dice.
    """
    kind = dict(weights.dtypes)["tid"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        win, total, size, dice = np.empty(k, dtype=object), -math.inf, np.zeros(k, dtype=np.int32), None
        for batch in batches:
            if not batch.num_rows:
                continue
            tid = np.array(batch.column("tid").to_pylist(), dtype=object)
            n, logw = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("n", "logw"))
            dice = dice or np.random.default_rng([seed, zlib.crc32(str(tid[0]).encode())])
            top = float(logw.max())
            run_to = np.cumsum(np.exp(logw - top))
            at = np.minimum(np.searchsorted(run_to, dice.random(k) * run_to[-1]), len(run_to) - 1)
            own = top + math.log(run_to[-1])
            both = np.logaddexp(total, own)
            new = dice.random(k) < math.exp(own - both)
            win[new], size[new], total = tid[at][new], n[at][new], both
        if total > -math.inf:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(k)), pa.array(win.tolist()), pa.array(size), pa.array(np.full(k, total))], ["draw_id", "tid", "n", "logw"])

    parts = weights.select("tid", "n", "logw").repartition("tid").sortWithinPartitions("tid").mapInArrow(run, f"draw_id long, tid {kind}, n int, logw double")
    key = F.col("logw") - F.ln(-F.ln(uniform(seed, F.col("draw_id"), F.col("tid"), F.col("logw"), "merge")))
    return parts.groupBy("draw_id").agg(F.max_by(F.struct("tid", "n"), key).alias("t")).select("draw_id", "t.tid", "t.n")


def draw_length(picks: DataFrame, f: LengthUtility, seed: int = 0) -> DataFrame:
    """``picks`` with the length ``l`` of each pattern; the law depends on n alone, so one small table serves all. Written once."""
    picks = written(picks, "picks")
    law = length_law(picks.sparkSession, known_sizes(picks), f, tail=1e-18)
    x = uniform(seed, F.col("draw_id"), "length")
    return picks.withColumn("x", x).join(F.broadcast(law), "n").where("x > lo and x <= hi").drop("x", "lo", "hi")


# --- items --------------------------------------------------------------------------------------------------------


def _mass(l: str, i: str, u: str) -> str:  # noqa: E741
    """Prefix mass: utility of all ways to pick l of the first i items on top of u."""
    return f"(if({i} < {l}, 0D, get(binom, greatest({i} - 1, 0) * 64 + {l} - 1) * get(s, {i} - 1) + get(binom, {i} * 64 + {l}) * {u}))"


def _guarded(rows: DataFrame) -> DataFrame:
    """``rows`` with binomials up to ``SQL_MOST``; a longer transaction ends the query rather than being drawn from wrongly."""
    table = rows.sparkSession.createDataFrame([([float(math.comb(i, x)) for i in range(64) for x in range(64)],)], "binom array<double>")
    short = F.when(F.size("items") > SQL_MOST, F.raise_error(F.lit(f"a transaction has more than {SQL_MOST} items: draw in Arrow"))).otherwise(F.col("items"))
    return rows.withColumn("items", short).crossJoin(F.broadcast(table))  # one row


def _uniform_sql(step: str, seed: int) -> str:
    return f"((cast(conv(substr(md5(concat_ws('|', '{seed}', draw_id, {step})), 1, 13), 16, 10) as double) + 0.5D) / 4503599627370496D)"


def jump_in_sql(rows: DataFrame, seed: int = 0) -> DataFrame:
    """(draw_id, tid, pattern, length): ``rows`` have draw_id, tid, l and packed items, w, s, n (n up to SQL_MOST).

    Each pick is one uniform and a binary search: the least position whose prefix mass reaches the scaled uniform. The next
    pick looks to the left of it.
    """
    search = (
        "aggregate(sequence(1, 7), named_struct('lo', st.rem - 1, 'hi', st.j), (b, x) -> if(b.hi - b.lo <= 1, b, "
        f"if({_mass('st.rem', '((b.lo + b.hi) div 2)', 'st.u')} >= goal, named_struct('lo', b.lo, 'hi', cast((b.lo + b.hi) div 2 as int)), named_struct('lo', cast((b.lo + b.hi) div 2 as int), 'hi', b.hi)))).hi"
    )
    pick = (
        "aggregate(sequence(1, l), named_struct('j', n, 'rem', l, 'u', 0D, 'pat', cast(array() as array<int>)), (st, step) -> "
        f"get(transform(transform(array({_uniform_sql('step', seed)} * {_mass('st.rem', 'st.j', 'st.u')}), goal -> {search}), "
        "i -> named_struct('j', i - 1, 'rem', st.rem - 1, 'u', st.u + get(w, i - 1), 'pat', concat(st.pat, array(i)))), 0)).pat"
    )
    full = _guarded(rows)
    got = full.select("draw_id", "tid", F.expr(f"array_sort(transform({pick}, i -> get(items, i - 1)))").alias("pattern"))
    return got.withColumn("length", F.size("pattern"))


def sequential_in_sql(rows: DataFrame, seed: int = 0) -> DataFrame:
    """The same law with a uniform for every item visited, from right to left; adds ``visited``."""
    stay = f"({_uniform_sql('i', seed)} * {_mass('st.rem', 'i', 'st.u')} > {_mass('st.rem', '(i - 1)', 'st.u')})"
    walk = (
        "aggregate(sequence(n, 1, -1), named_struct('rem', l, 'u', 0D, 'pat', cast(array() as array<int>), 'seen', 0), (st, i) -> if(st.rem = 0, st, "
        f"if({stay}, named_struct('rem', st.rem - 1, 'u', st.u + get(w, i - 1), 'pat', concat(st.pat, array(i)), 'seen', st.seen + 1), "
        "named_struct('rem', st.rem, 'u', st.u, 'pat', st.pat, 'seen', st.seen + 1))))"
    )
    full = _guarded(rows)
    got = full.select("draw_id", "tid", "items", F.expr(walk).alias("st"))
    return got.select("draw_id", "tid", F.expr("array_sort(transform(st.pat, i -> get(items, i - 1)))").alias("pattern"), F.col("st.seen").alias("visited")).withColumn("length", F.size("pattern"))


def whole_mass(s: list[int]) -> Callable[[int, int, int], int]:
    """The prefix mass of (l, i, u) in whole numbers of any size; ``s``: prefix sums from 0."""
    return lambda l, i, u: math.comb(i - 1, l - 1) * s[i] + math.comb(i, l) * u if i >= l else 0  # noqa: E741


def draw_exact(items: list, w: list, length: int | None, chance: Callable[[int], float]) -> list:
    """One pattern with whole numbers of any size; ``length`` None: drawn too, for summed utility without bounds."""
    order = sorted(range(len(items)), key=lambda i: items[i])
    s = [0]
    for i in order:
        s.append(s[-1] + int(w[i]))
    n = len(items)
    if length is None:
        goal, run, length = int(chance(0) * 2**53) * 2 ** (n - 1), 0, 0
        while length < n and (not length or run <= goal):
            length += 1
            run += math.comb(n - 1, length - 1) << 53
    mass = whole_mass(s)
    out, j, u = [], n, 0
    for left in range(length, 0, -1):
        goal = int(chance(length - left + 1) * 2**53) * mass(left, j, u)
        i = bisect.bisect_left(range(left, j + 1), goal, key=lambda i, left=left, u=u: mass(left, i, u) << 53) + left
        out.append(items[order[i - 1]])
        u += s[i] - s[i - 1]
        j = i - 1
    return sorted(out)


def grouped(picks: DataFrame, packed: DataFrame, *columns: str) -> DataFrame:
    """(tid, draws array<struct(draw_id, l)>, columns): a transaction stands once for every ``TOGETHER`` or so of its draws."""
    salts = F.ceil(F.count("*").over(Window.partitionBy("tid")) / TOGETHER)
    salted = picks.withColumn("salt", F.pmod(F.xxhash64("draw_id"), salts))
    rows = salted.groupBy("tid", "salt").agg(F.sort_array(F.collect_list(F.struct("draw_id", "l"))).alias("draws"))
    return rows.join(packed.select("tid", *columns), "tid").select("tid", "draws", *columns)


def in_arrow(rows: DataFrame, make: Callable[..., Callable[[int, int], tuple[list[int], int]]], arrays: tuple[str, ...]) -> DataFrame:
    """(draw_id, tid, pattern, length, visited) of grouped draws: ``make(arrays of one transaction)`` gives a function of
    (draw_id, length) that returns places of items and how many steps it took."""
    kinds = dict(rows.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["draw_id", "tid", "pattern", "length", "visited"]
        for batch in batches:
            out: list[tuple] = []
            for r in range(batch.num_rows):
                items = batch.column("items")[r].values
                draw = make(*(batch.column(c)[r].values.to_numpy(zero_copy_only=False) for c in arrays))
                tid = batch.column("tid")[r].as_py()
                for d in batch.column("draws")[r].as_py():
                    places, steps = draw(d["draw_id"], d["l"])
                    out.append((d["draw_id"], tid, items.take(pa.array(sorted(places), pa.int64())).to_pylist(), len(places), steps))
            types = (pa.int64(), batch.column("tid").type, batch.column("items").type, pa.int32(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t) for i, t in enumerate(types)], names)

    # Draws gather on few long transactions: they are spread by their first draw, not by transaction.
    spread = rows.withColumn("_first", F.col("draws")[0]["draw_id"]).repartition("_first").drop("_first")
    return spread.mapInArrow(run, f"draw_id long, tid {kinds['tid']}, pattern {kinds['items']}, length int, visited int")


_factorials = np.zeros(1)


def log_factorial(n: int) -> np.ndarray:
    """Logarithms of 0! to at least n!, one table for all transactions that a worker meets."""
    global _factorials
    if len(_factorials) <= n:
        _factorials = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, 2 * n + 2, dtype=float)))])
    return _factorials


def _log_masses(s: np.ndarray) -> Callable[[int, int, float], float]:
    """log of the prefix mass of (left, i, u), for left <= i."""
    lf = log_factorial(len(s))
    return lambda left, i, u: lf[i] - lf[left] - lf[i - left] + math.log(left * s[i - 1] / i + u)


def jump_in_arrow(rows: DataFrame, seed: int = 0) -> DataFrame:
    """The jump draw for transactions of any length: prefix masses in the log domain, over grouped draws. Steps: probes made."""
    from gleaner.functions.chance import uniform_value

    def make(s: np.ndarray, w: np.ndarray) -> Callable[[int, int], tuple[list[int], int]]:
        mass = _log_masses(s)

        def one(draw: int, length: int) -> tuple[list[int], int]:
            out, j, u, steps = [], len(s), 0.0, 0
            for left in range(length, 0, -1):
                goal = mass(left, j, u) + math.log(uniform_value(seed, draw, length - left + 1))
                lo, hi = left - 1, j
                while hi - lo > 1:
                    mid = (lo + hi) // 2
                    steps += 1
                    lo, hi = (lo, mid) if mass(left, mid, u) >= goal else (mid, hi)
                out.append(hi - 1)
                u += float(w[hi - 1])
                j = hi - 1
            return out, steps

        return one

    return in_arrow(rows, make, ("s", "w"))


def sequential_in_arrow(rows: DataFrame, seed: int = 0) -> DataFrame:
    """The sequential draw for transactions of any length. Steps: items visited."""
    from gleaner.functions.chance import uniform_value

    def make(s: np.ndarray, w: np.ndarray) -> Callable[[int, int], tuple[list[int], int]]:
        mass = _log_masses(s)

        def one(draw: int, length: int) -> tuple[list[int], int]:
            out, u, left, steps = [], 0.0, length, 0
            for i in range(len(s), 0, -1):
                if not left:
                    break
                steps += 1
                if i == left or math.log(uniform_value(seed, draw, i)) + mass(left, i, u) > mass(left, i - 1, u):
                    out.append(i - 1)
                    u += float(w[i - 1])
                    left -= 1
            return out, steps

        return one

    return in_arrow(rows, make, ("s", "w"))


def seed_split(picks: DataFrame, qdb: DataFrame, seed: int = 0) -> DataFrame:
    """The same law on long rows, for transactions too long for an array: one item in proportion to weight, the others evenly."""
    rows = picks.join(qdb, "tid").withColumn("race", -F.ln(uniform(seed, F.col("draw_id"), F.col("item"), "seed")) / F.col("w"))
    first = rows.groupBy("draw_id").agg(F.min_by("item", "race").alias("seed_item"))
    rows = rows.join(first, "draw_id").withColumn("order", F.when(F.col("item") == F.col("seed_item"), -1.0).otherwise(uniform(seed, F.col("draw_id"), F.col("item"), "rest")))
    rank = F.row_number().over(Window.partitionBy("draw_id").orderBy("order", "item"))
    kept = rows.withColumn("rank", rank).where("rank <= l")
    return kept.groupBy("draw_id", "tid").agg(F.array_sort(F.collect_list("item")).alias("pattern")).withColumn("length", F.size("pattern"))


def path_probability(items: list, w: list, pattern: list, f_length_share: float = 1.0) -> float:
    """Probability of one pattern as the product of accept and reject ratios from right to left, for any length."""
    s = np.cumsum(np.asarray(w, dtype=float))
    mass, held = _log_masses(s), set(pattern)
    left, u, p = len(pattern), 0.0, f_length_share
    for i in range(len(items), 0, -1):
        if not left:
            break
        stay = math.exp(mass(left, i - 1, u) - mass(left, i, u)) if i > left else 0.0
        if items[i - 1] in held:
            p, left, u = p * (1 - stay), left - 1, u + w[i - 1]
        else:
            p *= stay
    return p
