"""Repeated byte passages by suffix arrays and longest-previous-factor arrays, across all documents.

Every window of ``WINDOW`` bytes has one anchor: its 32-byte string of least hash (leftmost of equals). Equal windows
have equal anchors at equal places, so only windows of one anchor hash can be equal, wherever they stand. Anchors
(about one in 85 bytes) are counted first; the bytes around those seen twice are brought together, equal contexts
combined, and each group's contexts are sorted as suffixes; previous and next smaller positions in suffix order give the
longest previous factor of each window. A group with very many different contexts is settled window by window instead,
with map-side combined counts of 128-bit window hashes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gleaner.llm.common import binary_column, quoted
from gleaner.operators.components import HEAVY, spread_join
from gleaner.sources.shared import dropped, written

WINDOW, GRAM = 200, 32
#: Different contexts of one anchor above which windows are counted one by one.
CROWD = 4000
#: Anchors of one hash that are never too many for a task.
SPREAD = 1000
CHUNK = 1 << 21
_R = np.uint64(0x9E3779B97F4A7C15 | 1)
_RINV = np.uint64(pow(int(_R), -1, 1 << 64))
_S = np.uint64(0xC2B2AE3D27D4EB4F)
_SINV = np.uint64(pow(int(_S), -1, 1 << 64))
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power(base: np.uint64, inverse: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse, modulo 2**64."""
    have = _powers.get(int(base))
    if have is None or len(have[0]) < n:
        size = max(n, CHUNK + 1024)
        have = _powers[int(base)] = tuple(np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, x, dtype=np.uint64)]), dtype=np.uint64) for x in (base, inverse))
    return have


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(32))


def _prefix(data: np.ndarray, base: np.uint64, inverse: np.uint64) -> tuple[np.ndarray, np.ndarray]:
    up, down = _power(base, inverse, len(data) + 1)
    total = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=total[1:])
    return total, down


def _least(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each ``width`` neighbours, by doubling."""
    span, y = 1, x
    while 2 * span <= width:
        y = np.minimum(y[: len(y) - span], y[span:])
        span *= 2
    rest = width - span
    return np.minimum(y[: len(y) - rest], y[rest:]) if rest else y


def anchors(data: bytes, ends: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, ...]:
    """(hash, context hash, first window, windows) of each anchor; ``ends``: where the documents in ``data`` end."""
    none = np.zeros(0, dtype=np.int64)
    if len(data) < window:
        return none, none, none, none
    raw = np.frombuffer(data, dtype=np.uint8)
    total, down = _prefix(raw, _R, _RINV)
    gram = _mix((total[GRAM:] - total[:-GRAM]) * down[: len(total) - GRAM])
    low = np.uint64((1 << 24) - 1)
    least = _least((gram & ~low) | np.arange(len(gram), dtype=np.uint64), window - GRAM + 1)
    inside = np.ones(len(raw) + 1, dtype=bool)
    starts = np.concatenate([[0], ends[:-1]])
    for lo, hi in zip(np.maximum(starts, ends - window + 1).tolist(), ends.tolist(), strict=True):
        inside[lo:hi] = False
    at = np.flatnonzero(inside[: len(least)])
    if not len(at):
        return none, none, none, none
    own = (least[at] & low).astype(np.int64)
    cut = np.flatnonzero(np.diff(own, prepend=-1))
    first, n, own = at[cut], np.diff(np.append(cut, len(at))), own[cut]
    stop = first + n + window - 1
    context = _mix((total[stop] - total[first]) * down[first] + _mix((n * 1024 + own - first).astype(np.uint64)))
    return gram[own].view(np.int64), context.view(np.int64), first, n


def _portions(texts: list[bytes], window: int) -> Iterator[tuple[bytes, np.ndarray, np.ndarray, np.ndarray]]:
    """Texts joined up to CHUNK bytes, longer ones in overlapping parts: data, ends, index and shift of each text."""
    held: list[tuple[int, int, bytes]] = []
    size = 0
    for i, text in enumerate(texts):
        for lo in range(0, max(len(text) - window + 1, 0), CHUNK):
            part = text[lo : lo + CHUNK + window - 1]
            if size + len(part) > CHUNK and held:
                yield b"".join(x[2] for x in held), np.cumsum([len(x[2]) for x in held]), np.array([x[0] for x in held]), np.array([x[1] for x in held])
                held, size = [], 0
            held.append((i, lo, part))
            size += len(part)
    if held:
        yield b"".join(x[2] for x in held), np.cumsum([len(x[2]) for x in held]), np.array([x[0] for x in held]), np.array([x[1] for x in held])


def _anchor_rows(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, key = batch.column("doc_id"), batch.column("_k")
            for data, ends, index, shift in _portions(list(binary_column(batch, "text")), window):
                h, c, first, n = anchors(data, ends, window)
                which = np.searchsorted(ends, first, side="right")
                lo = first - np.concatenate([[0], ends[:-1]])[which] + shift[which]
                take = pa.array(index[which])
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(c), doc.take(take), key.take(take), pa.array(lo), pa.array(n.astype(np.int64))], ["h", "c", "doc_id", "_k", "lo", "n"])

    return run


# --- suffix arrays ------------------------------------------------------------------------------------------------


def _ranks(key: np.ndarray) -> np.ndarray:
    order = np.argsort(key, kind="stable")
    new = np.empty(len(key), dtype=np.uint64)
    new[order] = np.cumsum(np.diff(key[order], prepend=key[order[:1]]) != 0).astype(np.uint64)
    return new


def _paired(rank: np.ndarray, step: int) -> np.ndarray:
    """Keys of twice the depth: own rank, then that ``step`` further (0 past the end)."""
    after = np.zeros(len(rank), dtype=np.uint64)
    after[: max(len(rank) - step, 0)] = rank[step:] + np.uint64(1)
    return (rank << np.uint64(32)) | after


def suffix_order(data: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions in the order of their suffixes to ``depth`` bytes (ties by position), and their ranks, by prefix doubling."""
    key = np.zeros(len(data), dtype=np.uint64)
    step = min(8, 1 << (depth.bit_length() - 1))
    for i in range(step):
        key[: max(len(data) - i, 0)] |= data[i:].astype(np.uint64) << np.uint64(8 * (step - 1 - i))
    rank = _ranks(key)
    while step < depth:
        move = min(step, depth - step)
        rank = _ranks(_paired(rank, move))
        step += move
    return np.argsort(rank, kind="stable"), rank


def longest_previous_factors(order: np.ndarray, common: np.ndarray) -> np.ndarray:
    """For each position, the longest common prefix with an earlier one.

    ``order``: positions in suffix order; ``common[i]``: common prefix of order[i-1] and order[i]. The nearest smaller
    positions before and after in suffix order are found by following links, all at once; each link carries the least
    common prefix that it passes.
    """
    best = np.zeros(len(order), dtype=np.int64)
    for turn in (False, True):
        pos = order[::-1] if turn else order
        lcp = np.concatenate([[0], common[1:][::-1]]) if turn else common.copy()
        if len(lcp):
            lcp[0] = 0
        link, low = np.arange(len(pos)) - 1, lcp.astype(np.int64)
        todo = np.flatnonzero((link >= 0) & (low > 0))
        todo = todo[pos[link[todo]] > pos[todo]]
        while len(todo):
            via = link[todo]
            low[todo], link[todo] = np.minimum(low[todo], low[via]), link[via]
            todo = todo[(link[todo] >= 0) & (low[todo] > 0)]
            todo = todo[pos[link[todo]] > pos[todo]]
        found = np.where(link >= 0, low, 0)
        best[pos] = np.maximum(best[pos], found)
    return best


def _runs(flags: np.ndarray) -> list[int]:
    """Flat [start, stop, start, stop ...] of the true stretches."""
    return np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))).tolist()


def repeated_windows(contexts: list[bytes], window: int, both: bool = True) -> list[tuple[list[int], list[int]]]:
    """For each context (in order of first place), stretches of windows that stand in another one, and in an earlier one.

    The longest previous factor of a place tells whether its window stands earlier, that of the mirrored order of places
    whether it stands later; ``both``: whether the latter is asked for.
    """
    data = np.frombuffer(b"".join(contexts), dtype=np.uint8)
    size = np.array([len(c) for c in contexts])
    starts = np.concatenate([[0], np.cumsum(size)[:-1]])
    order, rank = suffix_order(data, window)
    inside = np.ones(len(data), dtype=bool)  # windows must not leave their context
    for s, n in zip(starts.tolist(), size.tolist(), strict=True):
        inside[s + n - window + 1 : s + n] = False
    order = order[inside[order]]
    same = np.concatenate([[False], rank[order[1:]] == rank[order[:-1]]])
    common = np.where(same, window, 0)
    places = np.sort(order)
    rank_of = np.argsort(np.argsort(order)) if len(order) else order  # positions without gaps, in suffix order
    later, either = (np.zeros(len(data), dtype=bool) for _ in range(2))
    later[places] = longest_previous_factors(rank_of, common) >= window
    if both:  # the same seen from the end: what stands in a later place too
        either[places] = longest_previous_factors(len(order) - 1 - rank_of, common)[::-1] >= window
    either |= later
    return [(_runs(either[s : s + n - window + 1]), _runs(later[s : s + n - window + 1])) for s, n in zip(starts.tolist(), size.tolist(), strict=True)]


def _marks(window: int, both: bool):
    """Contexts sorted by (h, doc_id, lo) come in; groups may span batches. Marks go out."""
    names = ["h", "c", "either", "later"]

    def solve(rows: list[tuple]) -> pa.RecordBatch:
        got = repeated_windows([r[2] for r in rows], window, both)
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32()))
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(([r[0] for r in rows], [r[1] for r in rows], [g[0] for g in got], [g[1] for g in got]), kinds, strict=True)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        done: list[tuple] = []
        group: list[tuple] = []
        size = 0
        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in ("h", "c", "context")), strict=True):
                if group and group[-1][:2] == row[:2]:  # of a repeated row of the table
                    continue
                if group and group[0][0] != row[0]:
                    done += group
                    group = []
                    if size > CHUNK // 2:
                        yield solve(done)
                        done, size = [], 0
                group.append(row)
                size += len(row[2])
        if done or group:
            yield solve(done + group)

    return run


def _window_rows(window: int):
    """Each window of a context as a row of its own: (w1, w2) is its 128-bit hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                raw = np.frombuffer(batch.column("context")[at].as_py(), dtype=np.uint8)
                n = len(raw) - window + 1
                hashes = []
                for base, inverse in ((_R, _RINV), (_S, _SINV)):
                    total, down = _prefix(raw, base, inverse)
                    hashes.append(pa.array(_mix((total[window:] - total[:-window]) * down[:n]).view(np.int64)))
                same = [pa.array([batch.column(c)[at].as_py()] * n, pa.int64()) for c in ("h", "c", "doc_id", "lo")]
                yield pa.RecordBatch.from_arrays([*hashes, *same, pa.array(np.arange(n, dtype=np.int32))], ["w1", "w2", "h", "c", "doc_id", "lo", "i"])

    return run


def _contexts(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, text in enumerate(binary_column(batch, "text")):
                asked = batch.column("asked")[i].as_py()
                columns = [pa.array([a[c] for a in asked], pa.int64()) for c in ("h", "c", "lo", "kinds")]
                cut = pa.array([text[a["lo"] : a["lo"] + a["n"] + window - 1] for a in asked], pa.binary())
                yield pa.RecordBatch.from_arrays([*columns, pa.array([batch.column("doc_id")[i].as_py()] * len(asked), pa.int64()), cut], ["h", "c", "lo", "kinds", "doc_id", "context"])

    return run


def spans(docs: DataFrame, window: int = WINDOW, keep_first: bool = False, crowd: int = CROWD) -> DataFrame:
    """``docs`` (doc_id as BIGINT, text, _k and more) with ``_cut``: flat [lo, hi, lo, hi ...] byte stretches to remove, unsorted, or null."""
    rows = written(docs.select("doc_id", "_k", "text").mapInArrow(_anchor_rows(window), "h long, c long, doc_id long, _k long, lo long, n long"), "anchors")
    heavy = max(int(rows.count() * HEAVY), SPREAD)  # anchors of one hash above which it is broadcast: fewer than 1 / HEAVY hashes
    all_rows, twice = rows, written(rows.groupBy("h").agg(F.count("*").alias("m")).where("m > 1"), "hashes")
    rows = written(spread_join(rows, twice, ["h"], F.col("m") > heavy).drop("m"), "anchors")
    dropped(all_rows)
    kinds = rows.groupBy("h", "c").agg(F.count("*").alias("m"), F.min(F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "lo", "_k", "n")).alias("first"))
    kinds = written(kinds, "kinds")
    mixed = kinds.groupBy("h").agg(F.count("*").alias("kinds")).where("kinds > 1")
    asked = spread_join(kinds, mixed, ["h"], F.col("kinds") > heavy).select("h", "c", "kinds", "first.*")
    asked = asked.groupBy("doc_id", "_k").agg(F.collect_list(F.struct("h", "c", "lo", "n", "kinds")).alias("asked"))  # at most one per 2 bytes of its document
    same = docs.doc_id.eqNullSafe(F.col("_d")) & (docs._k == F.col("_x"))
    asked = asked.withColumnsRenamed({"doc_id": "_d", "_k": "_x"})
    near = docs.join(asked, same).select("doc_id", "text", "asked").mapInArrow(_contexts(window), "h long, c long, lo long, kinds long, doc_id long, context binary")
    near = written(near, "contexts")
    few = near.where(F.col("kinds") <= crowd).repartition("h").sortWithinPartitions("h", F.asc_nulls_last("doc_id"), "lo", "c")
    marks = few.select("h", "c", "context").mapInArrow(_marks(window, not keep_first), "h long, c long, either array<int>, later array<int>")
    single = near.where(F.col("kinds") > crowd).dropDuplicates(["h", "c"]).mapInArrow(_window_rows(window), "w1 long, w2 long, h long, c long, doc_id long, lo long, i int")
    place = F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "lo", "c")
    many = single.groupBy("w1", "w2").agg(F.count("*").alias("m"), F.min(place).alias("least")).where("m > 1")
    step = F.array(F.col("i"), F.col("i") + 1)
    found = single.join(many, ["w1", "w2"]).groupBy("h", "c").agg(F.flatten(F.collect_list(step)).alias("either"), F.flatten(F.collect_list(F.when(place > F.col("least"), step))).alias("later"))
    kinds = kinds.join(marks.unionByName(found), ["h", "c"], "left").select("h", "c", "m", F.col("first.doc_id").alias("_fd"), F.col("first.lo").alias("_fl"), F.col("later" if keep_first else "either").alias("part"))
    kinds = written(kinds.where("m > 1 or size(part) > 0"), "marks")
    hit = spread_join(rows, kinds, ["h", "c"], F.col("m") > heavy)
    whole = ~(F.col("doc_id").eqNullSafe(F.col("_fd")) & (F.col("lo") == F.col("_fl"))) if keep_first else F.col("m") > 1
    part = F.when(whole, F.array(F.lit(0), F.col("n").cast("int"))).otherwise(F.coalesce("part", F.array().cast("array<int>")))
    moved = F.transform(part, lambda x, i: x + F.col("lo") + F.when(i % 2 == 1, window - 1).otherwise(0))
    cut = hit.select("doc_id", "_k", moved.alias("cut")).where("size(cut) > 0").groupBy("doc_id", "_k").agg(F.flatten(F.collect_list("cut")).alias("_cut"))
    cut = cut.withColumnsRenamed({"doc_id": "_d", "_k": "_x"})
    return docs.join(cut, docs.doc_id.eqNullSafe(F.col("_d")) & (docs._k == F.col("_x")), "left").drop("_d", "_x")


def remaining(text: bytes, cut: list[int] | None) -> tuple[bytes, int]:
    """What is left of a text, and the number of maximal removed stretches."""
    if not cut:
        return text, 0
    kept, at, n, end = [], 0, 0, -1
    for lo, hi in sorted(zip(cut[::2], cut[1::2], strict=True)):
        if lo > end:
            n += 1
            kept.append(text[at:lo])
        end = max(end, hi)
        at = max(at, hi)
    return b"".join([*kept, text[at:]]), n


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("doc_id", F.col("doc_id").cast("long")).withColumn("_k", F.xxhash64(F.col("doc_id"), F.col("text")))


def suffix_dedup(docs: DataFrame, window: int = WINDOW, keep_first: bool = False, crowd: int = CROWD) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of ``docs`` (doc_id, text).

    Removes each byte covered by a ``window``-byte string that also starts anywhere else (``keep_first``: that starts
    earlier, by doc_id and place). Null text is empty; shorter texts lose nothing; repeated rows count as documents of
    their own and are cut alike; a null doc_id is larger than any other; other columns are not read; empty stays empty.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cuts, out = batch.column("_cut").to_pylist(), []
            for text, cut in zip(binary_column(batch, "text"), cuts, strict=True):
                kept, n = remaining(text, cut)
                out.append((len(text), len(text) - len(kept), n, hashlib.sha256(kept).hexdigest()))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array([o[i] for o in out], t) for i, t in enumerate(kinds))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    done = spans(_keyed(docs.select("doc_id", "text")), window, keep_first, crowd)
    return done.select("doc_id", "text", "_cut").mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def cut_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` with all its columns; later copies of repeated passages are cut from ``text``, the first stays.

    ``n_chars``, if there is one, follows. A character that a cut goes through is dropped. Null text stays null and short
    texts stay whole; repeated rows are cut alike, and count as one when the first place of a passage is sought; a null
    doc_id is larger than any other; other columns may have any type or name; an empty table gives an empty one.
    """
    plain, schema = docs.columns, docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, cut in zip(batch.column("text").to_pylist(), batch.column("_cut").to_pylist(), strict=True):
                texts.append(remaining(text.encode(), cut)[0].decode("utf-8", "ignore") if cut else text)
            rest, columns = batch.column("rest"), []
            for name in plain:
                if name == "text":
                    columns.append(pa.array(texts, batch.column("text").type))
                elif name == "n_chars" and pa.types.is_integer(rest.field("n_chars").type):
                    columns.append(pa.array([None if t is None else len(t) for t in texts], rest.field("n_chars").type))
                else:
                    columns.append(rest.field(name))
            yield pa.RecordBatch.from_arrays(columns, plain)

    rest = F.struct(*[quoted(c) for c in plain if c != "text"]).alias("rest")  # so that no name can clash
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", rest, F.xxhash64("doc_id", "text").alias("_k"))
    return spans(keyed, window, True).select("text", "rest", "_cut").mapInArrow(run, schema)
