"""One-permutation MinHash fingerprints, in DataFrame functions only.

Each five-word shingle is hashed once; the high bits choose a bin and the least hash of a bin stays. Empty bins borrow
from full ones by optimal densification (each bin probes others in its own pseudo-random order). The low bits of each
bin are packed as text; likeness is the share of equal bins, corrected for agreement by chance.

A sorted array of hashes and one sentinel per bin gives the bins without an explode: the first entry of each bin is its
least hash, or the sentinel if the bin is empty.
"""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

WORDS, BINS, BITS, PROBES = 5, 256, 8, 12
#: "The next document" is found in buckets of doc_id, each one sorted run: quantiles of doc_id, cut further into equal widths
#: until a bucket has about ROWS rows. The first row of every bucket is broadcast as two numbers; MOST bounds that.
QUANTILES, ROWS, MOST = 400, 4096, 1_000_000
#: Shuffle partitions, above which each takes more buckets.
PARTITIONS = 100_000
_MASK = (1 << 56) - 1


def _ints(values: list[int], kind: str = "int") -> str:
    return f"array({','.join(f'cast({v} as {kind})' for v in values)})"


def _probes(probes: int) -> list[list[int]]:
    """For each probe, the bin that each bin looks at (0-based)."""
    dice = random.Random(20240229)
    return [[dice.randrange(BINS) for _ in range(BINS)] for _ in range(probes)]


def with_bins(df: DataFrame, text: str, out: str) -> DataFrame:
    """``df`` with ``out``: array<tinyint>, the low bits of each bin (less 128) of the column ``text``; null text is empty."""
    keep = df.columns
    sentinels = _ints([((j - 127) << 56) - 1 for j in range(BINS)], "bigint")
    looks = "".join(f"nullif(get(__d, get({_ints(p)}, j)) | if((get(__d, get({_ints(p)}, j)) & {_MASK}L) = {_MASK}L, -1L, 0L), -1L), " for p in _probes(PROBES))
    # Words, then one hash a word, then one hash a shingle.
    df = df.withColumn("__w", F.expr(f"transform(array_remove(split(lower(coalesce({text}, '')), '[^\\\\p{{L}}\\\\p{{N}}]+'), ''), w -> xxhash64(w))"))
    window = ", ".join(f"get(__w, i + {k})" for k in range(WORDS))
    df = df.select(*keep, F.expr(f"CASE WHEN size(__w) >= {WORDS} THEN transform(sequence(0, size(__w) - {WORDS}), i -> xxhash64({window})) WHEN size(__w) > 0 THEN array(xxhash64(__w)) ELSE cast(array() as array<bigint>) END").alias("__h"))
    df = df.select(*keep, F.expr(f"sort_array(concat(__h, {sentinels}))").alias("__s"))
    df = df.select(*keep, F.expr("filter(__s, (x, i) -> i = 0 or shiftright(x, 56) <> shiftright(get(__s, i - 1), 56))").alias("__d"))
    full = f"filter(__d, x -> (x & {_MASK}L) <> {_MASK}L)"
    df = df.select(*keep, "__d", F.expr(full).alias("__f"))
    last = "array_min(transform(__f, x -> struct(xxhash64(j, shiftright(x, 56)) AS o, x AS v))).v"
    filled = f"transform(__d, (v, j) -> if((v & {_MASK}L) <> {_MASK}L or size(__f) = 0, v, coalesce({looks} {last})))"
    return df.select(*keep, F.expr(f"transform({filled}, v -> cast((v & {(1 << BITS) - 1}L) - 128 as tinyint))").alias(out))


def packed(bins: Column) -> Column:
    """Fingerprint as text: two hex digits a bin."""
    return F.array_join(F.transform(bins, lambda b: F.lpad(F.lower(F.hex(b.cast("int") + 128)), 2, "0")), "")


def likeness(a: Column, b: Column) -> Column:
    """Estimated Jaccard likeness of two fingerprints, 0 to 1, without the agreement that chance gives."""
    equal = F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda same: same)) / BINS
    chance = 1 / (1 << BITS)
    return F.when(a == b, 1.0).otherwise(F.greatest(F.lit(0.0), (equal - chance) / (1 - chance)))


def _quantile(cuts: list[int], id_: str) -> str:
    """SQL of the number of ``cuts`` below ``id_``, looked up in two steps."""
    wide = max(1, int(len(cuts) ** 0.5))
    blocks = [cuts[i : i + wide] for i in range(0, len(cuts), wide)]
    tops, nested = _ints([b[-1] for b in blocks], "bigint"), f"array({','.join(_ints(b, 'bigint') for b in blocks)})"
    high = f"size(filter({tops}, c -> c < {id_}))"
    return f"({high} * {wide} + coalesce(size(filter(get({nested}, {high}), c -> c < {id_})), 0))"


def _bucketed(docs: DataFrame, rows: int) -> tuple[str, DataFrame, int]:
    """SQL of the bucket of a doc_id, larger ids in larger buckets; (top, bucket): the largest doc_id of each bucket and the bucket that comes before it in descending order; the number of rows."""
    spread = docs.agg(F.count("*").alias("n"), F.min("doc_id").alias("low"), F.max("doc_id").alias("high"), F.percentile_approx("doc_id", [i / QUANTILES for i in range(1, QUANTILES)], 10_000).alias("cuts")).first()
    cuts, id_ = sorted(set(spread.cuts or [])), "coalesce(doc_id, -9223372036854775808)"
    parts = max(1, min(-(-spread.n // (QUANTILES * rows)), MOST // QUANTILES))
    if cuts:
        edges = [float(x) for x in (spread.low, *cuts, spread.high)]
        q = _quantile(cuts, id_)
        docs = docs.withColumn("q", F.expr(q))
        low, wide = (f"array({','.join(f'{x!r}D' for x in xs)})" for xs in (edges[:-1], [max(b - a, 1.0) for a, b in zip(edges, edges[1:], strict=False)]))
        # In doubles, whose rounding keeps the order.
        place = f"cast({q} * {parts} + greatest(0, least({parts - 1}, floor((cast({id_} as double) - get({low}, {q})) / get({wide}, {q}) * {parts}))) as int)"
    else:
        docs, place = docs.withColumn("q", F.lit(0)), "0"
    tops = docs.groupBy("q", F.expr(place).alias("b")).agg(F.max("doc_id").alias("top"))
    ends = tops.groupBy("q").agg(F.min("b").alias("b")).orderBy(F.desc("q")).collect()  # one row a quantile
    ahead = F.create_map(*[F.lit(x).cast("int") for i, r in enumerate(ends) for x in (r.q, ends[i - 1].b)]) if ends else F.lit(None)
    before = F.lag("b").over(Window.partitionBy("q").orderBy(F.desc("b")))
    return place, tops.select("top", F.coalesce(before, ahead[F.col("q")] if ends else F.lit(0)).alias("bucket")), spread.n


def fingerprints(docs: DataFrame, bucket_rows: int = ROWS) -> DataFrame:
    """For every row of ``docs`` (doc_id, text): doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text: the last floor(n_chars / 2) code points replaced by as many (or all) of the first of the next
    document in descending doc_id (after the last: the first). Null text is empty, without a shingle: all such texts are
    alike and unlike any other. Fewer than five words make one shingle. Rows that repeat a doc_id follow each other in a
    fixed order of their texts, a null doc_id comes last; other columns are not read; an empty table gives an empty one.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    place, tops, n = _bucketed(docs.select("doc_id"), bucket_rows)
    rows = docs.withColumn("bucket", F.expr(place)).withColumn("copy", F.lit(0))
    # The first row of each bucket is also put at the end of the bucket before it, so that no row looks outside its bucket.
    heads = docs.join(F.broadcast(tops), F.col("doc_id").eqNullSafe(F.col("top"))).select("doc_id", "text", "bucket", F.lit(1).alias("copy"))
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(PARTITIONS, -(-n // ROWS)))
    binned = with_bins(rows.unionByName(heads), "text", "bins").repartition(parts, "bucket")
    order = Window.partitionBy("bucket").orderBy("copy", F.desc_nulls_last("doc_id"), F.xxhash64("text"))
    following = binned.withColumn("next_text", F.lead("text").over(order)).withColumn("next_bins", F.lead("bins").over(order)).where("copy = 0")
    size = F.char_length("text")
    edited = F.expr("concat(left(text, n_chars - n_chars div 2), left(coalesce(next_text, ''), cast(n_chars div 2 as int)))")
    done = following.select("doc_id", "bins", "next_bins", size.alias("n_chars"), "text", "next_text").select("doc_id", "bins", "next_bins", "n_chars", edited.alias("edited"))
    done = with_bins(done, "edited", "edited_bins")
    return done.select(
        "doc_id", F.col("n_chars").cast("long").alias("n_chars"), F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        packed(F.col("bins")).alias("fingerprint"), packed(F.col("edited_bins")).alias("edited_fingerprint"),
        likeness(F.col("bins"), F.col("edited_bins")).alias("near_edited"), likeness(F.col("bins"), F.col("next_bins")).alias("near_next"),
    )
