"""SentencePiece encoding and decoding with seeded merge dropout.

An agenda of candidate merges joins the best pair of each word first, as the merge-type model prescribes; the agendas of
many words advance together in numpy. With dropout, each candidate is skipped if the keyed hash of (seed, document, place of
the chunk, place in the chunk, pair) falls below the rate, so that every occurrence of a word has dice of its own and any
task can make them again. Only segmentations without dropout are kept. All segmentations decode to the text they came from.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gleaner.llm.common import text_column
from gleaner.llm.merges import MergeTable

SEED, RATE = 20240601, 0.1
#: Bounds of memory: chunks without dropout that are kept, characters of texts that advance together.
CACHE, TOGETHER = 400_000, 1_000_000
#: Fixed value: the mark that stands for a blank in pieces.
BLANK = "▁"
#: No piece goes on after a blank that follows something else, nor over a line end.
CHUNK = re.compile(r" *[^ \n]+| +|\n")


def model_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    for by in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F):
        x = (x ^ (x >> np.uint64(32))) * np.uint64(by)
    return x


class Pieces:
    """The vocabulary of a merge-type model, and its agenda of merges."""

    def __init__(self, path: str) -> None:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = self.n = model.get_piece_size()
        names = [model.id_to_piece(i) for i in range(n)]
        self.bytes = {int(names[i][3:5], 16): i for i in range(n) if model.is_byte(i)}
        plain = [i for i in range(n) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        self.ids = {names[i]: i for i in plain}
        splits = [(self.ids[a], self.ids[b], i) for i in plain for k in range(1, len(names[i])) if (a := names[i][:k]) in self.ids and (b := names[i][k:]) in self.ids]
        order = {i: k for k, i in enumerate(sorted(plain, key=lambda i: (-model.get_score(i), i)))}
        self.table = MergeTable(*(np.array(x) for x in zip(*((a, b, order[i], i) for a, b, i in splits), strict=True)))
        raw = [b""] * n
        for i in plain:
            raw[i] = names[i].replace(BLANK, " ").encode()
        for b, i in self.bytes.items():
            raw[i] = bytes([b])
        self.size, self.flat = np.array([len(r) for r in raw]), np.frombuffer(b"".join(raw), dtype=np.uint8)
        self.first = np.cumsum(self.size) - self.size
        self.codes = np.full(0x110000, -1, dtype=np.int64)  # of single characters; others go beyond the vocabulary, to become bytes
        for name, i in self.ids.items():
            if len(name) == 1:
                self.codes[ord(name)] = i
        self.codes[ord(BLANK)] = -1  # in a text it is no blank
        self.codes[ord(" ")] = self.ids[BLANK]
        self.codes = np.where(self.codes < 0, n + np.arange(0x110000), self.codes)

    def encode(self, chunks: list[str], skip: Callable | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids, chunk number of each) of all chunks; ``skip`` as in MergeTable.segment."""
        size = np.fromiter(map(len, chunks), dtype=np.int64, count=len(chunks))
        symbols = self.codes[np.frombuffer("".join(chunks).encode("utf-32-le", "surrogatepass"), dtype="<u4")]
        ids, word = self.table.segment(symbols, np.repeat(np.arange(len(chunks)), size), skip)
        strange = np.flatnonzero(ids >= self.n)
        if len(strange):
            spelt = [[self.bytes[b] for b in chr(int(x) - self.n).encode("utf-8", "surrogatepass")] for x in ids[strange]]
            times = np.ones(len(ids), dtype=np.int64)
            times[strange] = [len(x) for x in spelt]
            at = np.repeat(ids >= self.n, times)
            ids, word = np.repeat(ids, times), np.repeat(word, times)
            ids[at] = [b for x in spelt for b in x]
        return ids, word

    def spelt(self, ids: np.ndarray) -> tuple[bytes, np.ndarray]:
        """The bytes that ids stand for, joined, and where those of each id end."""
        size = self.size[ids]
        ends = np.cumsum(size)
        if not len(ids):
            return b"", ends
        return self.flat[np.arange(ends[-1]) + np.repeat(self.first[ids] - ends + size, size)].tobytes(), ends

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids: pieces joined, less the blank put before the first."""
        raw = self.spelt(ids)[0]
        return (raw[1:] if raw[:1] == b" " else raw).decode("utf-8", "replace")


@lru_cache(maxsize=1)
def pieces(path: str) -> Pieces:
    """One for all tasks of a worker process."""
    return Pieces(path)


def chunks(text: str) -> list[str]:
    """Parts of a text that no piece crosses; the first has the blank that the model puts before a text."""
    return CHUNK.findall(" " + text) if text else []


class Encoder:
    """Whole texts; segmentations without dropout are kept up to a bound, those with it are made for each occurrence."""

    def __init__(self, pieces: Pieces, seed: int, rate: float) -> None:
        self.pieces, self.seed, self.rate = pieces, seed, rate
        self.plain: dict[str, bytes] = {}

    def _plain(self, parts: list[str]) -> list[bytes]:
        """Ids (little-endian uint32 bytes) of each chunk."""
        if len(self.plain) > CACHE:
            self.plain.clear()
        got = list(map(self.plain.get, parts))
        new = {c for c, x in zip(parts, got, strict=True) if x is None}
        if new:
            ids, chunk = self.pieces.encode(list(new))
            flat = ids.astype("<u4").tobytes()
            cut = [0, *(4 * np.cumsum(np.bincount(chunk, minlength=len(new)))).tolist()]
            self.plain.update(zip(new, (flat[a:b] for a, b in zip(cut, cut[1:], strict=False)), strict=True))
            got = list(map(self.plain.__getitem__, parts))
        return got

    def _varied(self, parts: list[str], count: np.ndarray, docs: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """Ids with dropout of all texts, and where each text ends; chunks of many texts advance together."""
        base = np.array([xxhash.xxh64_intdigest(str(d), self.seed) for d in docs], dtype=np.uint64)
        place = np.arange(len(parts)) - np.repeat(np.cumsum(count) - count, count)
        keys = mixed(np.repeat(base, count) + place.astype(np.uint64) * GOLDEN)
        below = np.uint64(int(self.rate * 2.0**53))

        def skip(word: np.ndarray, place: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
            x = mixed(keys[word] + place.astype(np.uint64) * GOLDEN)
            x = mixed(x ^ ((left.astype(np.uint64) << np.uint64(32)) | right.astype(np.uint64)))
            return (x >> np.uint64(11)) < below

        ids, chunk = self.pieces.encode(parts, skip)
        return ids, np.searchsorted(chunk, np.cumsum(count))

    def __call__(self, texts: list[str], docs: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(ids, ends, varied, ends): of all texts together without and with dropout; ``docs``: the documents' keys for the dice."""
        split = [chunks(t) for t in texts]
        parts = [c for text in split for c in text]
        count = np.array([len(t) for t in split], dtype=np.int64)
        plain = self._plain(parts)
        size = np.fromiter(map(len, plain), dtype=np.int64, count=len(plain)) // 4
        ends = np.concatenate([[0], np.cumsum(size)])[np.cumsum(count)]
        ids = np.frombuffer(b"".join(plain), dtype="<u4").astype(np.int64)
        return ids, ends, *(self._varied(parts, count, docs) if self.rate and parts else (ids, ends))


SCHEMA = "doc_id long, n_pieces long, ids_crc32 long, n_varied long, varied_crc32 long, lossless boolean, decoded_sha256 string"


def _batches(batch: pa.RecordBatch) -> Iterator[tuple[pa.RecordBatch, list[int], list[str]]]:
    """Some rows at a time: at most ``TOGETHER`` characters beyond the first row."""
    keys, texts = [-1 if d is None else d for d in batch.column("doc_id").to_pylist()], list(text_column(batch, "text"))
    lo = size = 0
    for i, text in enumerate(texts):
        if i > lo and size + len(text) > TOGETHER:
            yield batch.slice(lo, i - lo), keys[lo:i], texts[lo:i]
            lo, size = i, 0
        size += len(text)
    if lo < len(texts):
        yield batch.slice(lo), keys[lo:], texts[lo:]


def encode(docs: DataFrame, model: str | None = None, seed: int = SEED, rate: float = RATE) -> DataFrame:
    """(doc_id, ids, varied): ids without and with dropout, for every row of ``docs`` (doc_id, text); null text gives no ids."""
    path = model or model_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(pieces(path), seed, rate)
        numbers = lambda ids, ends: pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(ids, pa.int32()))
        for batch in batches:
            for part, keys, texts in _batches(batch):
                ids, ends, varied, varied_ends = encoder(texts, keys)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), numbers(ids, ends), numbers(varied, varied_ends)], ["doc_id", "ids", "varied"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, ids array<int>, varied array<int>")


def sides(encoder: Encoder, texts: list[str], keys: list[int]) -> Iterator[list[tuple[memoryview, bytes]]]:
    """For the plain and for the varied encoding: (ids as little-endian uint32 bytes, bytes they decode to) of each text."""
    both = encoder(texts, keys)
    for ids, ends in (both[:2], both[2:]):
        flat, (raw, stops) = memoryview(ids.astype("<u4").tobytes()), encoder.pieces.spelt(ids)
        cut, stop = [0, *ends.tolist()], [0, *np.concatenate([[0], stops])[ends].tolist()]
        # Less the blank that the model puts before a text.
        yield [(flat[4 * a : 4 * b], raw[x + (raw[x : x + 1] == b" ") : y] if y > x else b"") for a, b, x, y in zip(cut, cut[1:], stop, stop[1:], strict=False)]


def row(text: str, plain: tuple[memoryview, bytes], varied: tuple[memoryview, bytes]) -> tuple:
    lossless = varied[1] == text.encode() == plain[1]
    return len(plain[0]) // 4, zlib.crc32(plain[0]), len(varied[0]) // 4, zlib.crc32(varied[0]), lossless, hashlib.sha256(varied[1]).hexdigest()


def round_trip(docs: DataFrame, model: str | None = None, seed: int = SEED, rate: float = RATE) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): sizes and checksums of both encodings, and what the varied one decodes to.

    Ids are hashed as little-endian unsigned 32-bit numbers. Null text is empty: no pieces, lossless. The same seed and
    doc_id give the same ids wherever a row is processed; repeated rows agree; a null doc_id counts as -1 for the dice
    and stays null; other columns are not read; an empty table gives an empty one.
    """
    path = model or model_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(pieces(path), seed, rate)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.string())
        names = [c.split()[0] for c in SCHEMA.split(", ")][1:]
        for batch in batches:
            for part, keys, texts in _batches(batch):
                rows = [row(t, p, v) for t, p, v in zip(texts, *sides(encoder, texts, keys), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], ["doc_id", *names])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, SCHEMA)
