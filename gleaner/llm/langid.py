"""Language identification, word first: log frequency of known words per language, and for unseen words ever
shorter character n-grams."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gleaner.llm.common import held_out, text_column

#: Parameters of the model: documents to learn from (chosen by hash), words kept, longest n-gram.
MAX_TRAIN, MAX_WORDS, LONGEST = 30_000, 150_000, 5
CACHE = 300_000
#: A word: letters, each with the marks that combine with it. ASCII texts need no tables of categories.
WORD, ASCII_WORD = regex.compile(r"(?:\p{L}\p{M}*)+"), re.compile(r"[a-z]+")


def words_in(text: str) -> list[str]:
    """The words of a text, lower-cased."""
    text = text.lower()
    return ASCII_WORD.findall(text) if text.isascii() else WORD.findall(text)


def shares(counts: dict[str, int], bound: int) -> dict[str, float]:
    """The share of each language's rows so that about ``bound`` are taken: small languages whole, the others alike."""
    out, left = {}, bound
    for i, (lang, n) in enumerate(sorted(counts.items(), key=lambda x: (x[1], x[0]))):
        take = min(n, left / (len(counts) - i))
        out[lang], left = take / n, left - take
    return out


def train_rows(docs: DataFrame, bound: int = MAX_TRAIN) -> DataFrame:
    """(text, lang) of at most about ``bound`` documents that may be learned from, chosen by the hash of doc_id in each language."""
    may = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "text", "lang")
    counts = {r["lang"]: r["n"] for r in may.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # one row a language
    below = [(lang, int(share * (1 << 40))) for lang, share in shares(counts, bound).items()]
    cuts = docs.sparkSession.createDataFrame(below, "lang string, below long")
    return may.join(F.broadcast(cuts), "lang").where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) < F.col("below")).select("text", "lang")


def word_counts(rows: DataFrame, most: int = MAX_WORDS) -> list:
    """At most ``most`` (lang, word, n): of each language the words seen most, as many as of any other that has so many."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, Counter] = {}

        def flush() -> pa.RecordBatch:
            flat = [(lang, w, n) for lang, c in seen.items() for w, n in c.items()]
            seen.clear()
            return pa.RecordBatch.from_arrays([pa.array([x[i] for x in flat], t) for i, t in enumerate((pa.string(), pa.string(), pa.int64()))], ["lang", "word", "n"])

        for batch in batches:
            for text, lang in zip(text_column(batch, "text"), batch.column("lang").to_pylist(), strict=True):
                seen.setdefault(lang, Counter()).update(words_in(text))
            if sum(map(len, seen.values())) > 200_000:
                yield flush()
        yield flush()

    counted = rows.mapInArrow(run, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))
    return counted.withColumn("place", place).where(F.col("place") <= most).orderBy("place", F.desc("n"), "lang").limit(most).drop("place").collect()


class Model:
    """Scores of words: a row of log-likelihoods, one for each language in name order."""

    def __init__(self, counts: list) -> None:
        self.langs = sorted({r[0] for r in counts})
        at, width = {x: i for i, x in enumerate(self.langs)}, len({r[0] for r in counts})
        tables: list[dict[str, list[int]]] = [{} for _ in range(LONGEST + 1)]  # 0: words, else n-grams of that length
        for lang, word, n in counts:
            k, padded = at[lang], f"<{word}>"
            tables[0].setdefault(word, [0] * width)[k] += n
            for size in range(1, LONGEST + 1):
                for i in range(len(padded) - size + 1):
                    tables[size].setdefault(padded[i : i + size], [0] * width)[k] += n
        self.index: list[dict[str, int]] = []
        self.rows: list[np.ndarray] = []
        for table in tables:
            seen = np.array([*table.values()], dtype=float).reshape(len(table), width)
            self.index.append({key: i for i, key in enumerate(table)})
            self.rows.append(np.log((seen + 0.5) / (seen.sum(axis=0) + 0.5 * max(len(seen), 1))))

    def score(self, words: list[str]) -> np.ndarray:
        """A row for each word: its own, or the mean over its longest n-grams of which any was seen, or zeros."""
        out = np.zeros((len(words), len(self.langs)))
        known = [self.index[0].get(w, -1) for w in words]
        hit = np.flatnonzero(np.array(known) >= 0)
        out[hit] = self.rows[0][np.array(known)[hit]]
        open_words = [(i, f"<{w}>") for i, (w, k) in enumerate(zip(words, known, strict=True)) if k < 0]
        for size in range(LONGEST, 0, -1):
            index, found, owner, left = self.index[size], [], [], []
            for i, padded in open_words:
                rows = [r for k in range(len(padded) - size + 1) if (r := index.get(padded[k : k + size])) is not None]
                if rows:
                    found += rows
                    owner.append((i, len(rows)))
                else:
                    left.append((i, padded))
            if owner:
                n = np.array([x[1] for x in owner])
                sums = np.add.reduceat(self.rows[size][found], np.concatenate([[0], np.cumsum(n)[:-1]]), axis=0)
                out[[x[0] for x in owner]] = sums / n[:, None]
            open_words = left
        return out


def train(docs: DataFrame) -> Model:
    return Model([tuple(r) for r in word_counts(train_rows(docs))])


class Reader:
    """Applies a model to texts; rows of words met before are kept, up to a bound."""

    def __init__(self, model: Model) -> None:
        self.model, self.at, self.table = model, {}, np.zeros((CACHE, len(model.langs)))

    def __call__(self, texts: list[str]) -> list[tuple[str, float]]:
        return [self._one(words) for words in self._known([words_in(t) for t in texts])]

    def _known(self, split: list[list[str]]) -> Iterator[list[str]]:
        new = [w for w in set().union(*split) if w not in self.at]
        if len(self.at) + len(new) > CACHE:
            self.at.clear()
            new = list(set().union(*split))
        if len(new) <= CACHE and new and self.model.langs:
            first = len(self.at)
            self.table[first : first + len(new)] = self.model.score(new)
            self.at.update(zip(new, range(first, first + len(new)), strict=True))
        yield from split

    def _one(self, words: list[str]) -> tuple[str, float]:
        if not words or not self.model.langs:
            return "und", 0.0
        if all(map(self.at.__contains__, words)):
            total = self.table[np.fromiter(map(self.at.__getitem__, words), dtype=np.int64, count=len(words))].sum(axis=0)
        else:  # one text with more different words than are kept
            total = sum(self.model.score(words[i : i + 10_000]).sum(axis=0) for i in range(0, len(words), 10_000))
        best = int(total.argmax())
        # Words of one text are far from independent: evidence counts by its square root.
        odds = np.exp((total - total[best]) / np.sqrt(len(words)))
        return self.model.langs[best], float(1 / odds.sum())


def identify(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row of ``docs`` (doc_id, text, lang), from whole texts.

    Learns from text and non-null lang of rows that are not held out. Null text, or one without a letter, is ``und``
    with score 0; so is everything if nothing could be learned. Ties go to the first language by name. Repeated rows
    each get a row; other columns are not read; an empty table gives an empty one.
    """
    model = model or train(docs)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by MAX_WORDS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = Reader(shared.value)
        for batch in batches:
            texts = list(text_column(batch, "text"))
            got = [x for i in range(0, len(texts), 400) for x in read(texts[i : i + 400])]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array([x[0] for x in got], pa.string()), pa.array([x[1] for x in got], pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")
