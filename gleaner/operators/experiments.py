"""The measured experiments: seconds of preprocessing, milliseconds a pattern of drawing, speed-ups, sizes.

Preprocessing and drawing are timed apart, over a database that was written before. A refusal of the matrix baseline is a null.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gleaner.operators import jump, matrix, metrics, model, sampler
from gleaner.operators.lengths import LengthUtility
from gleaner.sources.shared import written

METHODS = ("jump", "matrix", "twopass")
ROW = "database string, method string, M int, prepare_s double, prepare_sd double, draw_ms double, draw_sd double"


def law(M: int | None) -> LengthUtility:  # noqa: N803
    return LengthUtility("mean", 1, M)


def preprocessing(qdb: DataFrame, method: str, M: int | None, repeats: int) -> tuple[float, float] | None:  # noqa: N803
    """Seconds, mean and deviation, until patterns can be drawn."""
    if method == "matrix":
        packed = model.pack(qdb)
        top = M or 1 << 30
        if matrix.cells(model.sizes(qdb), top).first().refused:
            return None
        return metrics.timed(lambda: matrix.stored(packed, M, budget=False), repeats)
    if method == "twopass":
        return metrics.timed(lambda: written(model.weights(qdb, law(M)), "weights"), repeats)
    return metrics.timed(lambda: model.weights(qdb, law(M)), repeats)


def drawing(qdb: DataFrame, method: str, M: int | None, k: int, repeats: int, seed: int = 0) -> tuple[float, float] | None:  # noqa: N803
    """Milliseconds a pattern, mean and deviation, of k patterns; weights (or matrices) are there already."""
    if method == "matrix":
        if matrix.cells(model.sizes(qdb), M or 1 << 30).first().refused:
            return None
        ready = matrix.stored(model.pack(qdb), M, budget=False)
        one = sampler.Sampler(qdb, law(M), seed, "disk")
        one.weights.count()
        took = metrics.timed(lambda: matrix.matrix_draw(one.picks(k, "prefix"), ready, seed, M), repeats)
    else:
        one = sampler.Sampler(qdb, law(M), seed, "disk" if method == "twopass" else "memory")
        one.weights.count()
        took = metrics.timed(lambda: one.sample(k, pick="prefix"), repeats)
    return 1000 * took[0] / k, 1000 * took[1] / k


def sweep(databases: dict[str, DataFrame], lengths: Iterable[int | None], k: int = 10_000, repeats: int = 10, methods: Iterable[str] = METHODS) -> DataFrame:
    """ROW for each database, method and longest length (null: without bounds)."""
    rows, spark = [], None
    for name, qdb in databases.items():
        qdb, spark = written(qdb.select("tid", "item", "w"), f"qdb-{name}"), qdb.sparkSession
        for M in lengths:  # noqa: N806
            for method in methods:
                p, d = preprocessing(qdb, method, M, repeats), drawing(qdb, method, M, k, repeats)
                rows.append((name, method, M, *(p or (None, None)), *(d or (None, None))))
    return spark.createDataFrame(rows, ROW)


def speed_up(times: DataFrame, over: str = "matrix", of: str = "jump") -> DataFrame:
    """(database, M, prepare, draw): how many times faster ``of`` is than ``over``."""
    side = lambda m, tag: times.where(F.col("method") == m).select("database", "M", F.col("prepare_s").alias(f"p_{tag}"), F.col("draw_ms").alias(f"d_{tag}"))
    a, b = side(over, "a"), side(of, "b").withColumnRenamed("database", "_d").withColumnRenamed("M", "_m")
    both = a.join(b, (F.col("database") == F.col("_d")) & F.col("M").eqNullSafe(F.col("_m")))
    return both.select("database", "M", (F.col("p_a") / F.col("p_b")).alias("prepare"), (F.col("d_a") / F.col("d_b")).alias("draw"))


def recursion_against_closed(qdb: DataFrame, repeats: int = 3) -> DataFrame:
    """(way, seconds, sd): all cells of the triangle in closed form, by recursion, and by the matrix baseline."""
    packed = written(model.pack(qdb), "packed")
    ways = {"closed": lambda: model.triangle(packed), "recursion": lambda: model.triangle_by_recursion(packed), "matrix": lambda: matrix.matrix_weights(packed, 1, 1 << 20)}
    return qdb.sparkSession.createDataFrame([(name, *metrics.timed(way, repeats)) for name, way in ways.items()], "way string, seconds double, sd double")


def sizes_on_disk(databases: dict[str, DataFrame]) -> DataFrame:
    """(database, rows, disk_bytes, memory_bytes): as written, and as Spark's plan expects it in memory."""
    rows, spark = [], None
    for name, qdb in databases.items():
        spark = qdb.sparkSession
        kept = written(qdb.select("tid", "item", "w"), f"qdb-{name}")
        jvm = spark._jvm.org.apache.hadoop.fs.Path
        conf = spark._jsc.hadoopConfiguration()
        disk = sum(p.getFileSystem(conf).getFileStatus(p).getLen() for p in map(jvm, kept.inputFiles()))
        cached = kept.persist()
        n = cached.count()
        memory = int(str(cached._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        cached.unpersist()
        rows.append((name, n, disk, memory))
    return spark.createDataFrame(rows, "database string, rows long, disk_bytes long, memory_bytes long")


def response(draw, repeats: int = 3) -> tuple[float, float]:  # noqa: ANN001
    """Seconds until a user sees a new sub-profile: ``draw()`` gives its (nodes, edges)."""
    return metrics.timed(lambda: draw()[1], repeats)
