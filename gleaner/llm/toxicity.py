"""Toxicity by a noisy channel: disguised words are restored by Viterbi decoding of a character lattice under a
character language model, then the restored words are scored.

The channel writes letters as look-alikes, repeats them, or sets them apart. The language model is counted over all
documents. The scorer is a small lexicon of words and word beginnings, learned from a bounded sample of labelled rows.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

from gleaner.llm.common import held_out, named, one, text_column
from gleaner.llm.merges import TwoAges

#: Parameters: labelled rows to learn from (chosen by hash of doc_id), candidate features, lexicon size, threshold.
MAX_TRAIN, MAX_CANDIDATES, MAX_LEXICON, THRESHOLD = 40_000, 20_000, 2_000, 0.3
CACHE = 300_000
#: Letters of the language model (0 is everything else), and what look-alikes may stand for.
LETTERS = "abcdefghijklmnopqrstuvwxyzßàáâäçèéêëíîïñóôöùúûü"
LOOKS = {"0": "o", "1": "il", "!": "i", "|": "il", "3": "e", "4": "a", "@": "a", "$": "s", "5": "s", "7": "t", "+": "t", "8": "b", "9": "g", "6": "g", "(": "c", "€": "e", "2": "z"}
A = len(LETTERS) + 1
_CODE = np.zeros(0x180, dtype=np.int64)
for _i, _c in enumerate(LETTERS):
    _CODE[ord(_c)] = _i + 1
_INDEX = {c: i + 1 for i, c in enumerate(LETTERS)}
#: A run of short tokens set apart by blanks or marks, and what sets them apart; what is cut off the ends of a token; a doubled letter.
_UNIT = rf"(?:[{re.escape(LETTERS + ''.join(LOOKS))}]{{1,2}}|([{re.escape(LETTERS + ''.join(LOOKS))}])\1{{2,}})"
GAP = re.compile(r"[\s.\-_*]+")
SPACED = re.compile(rf"(?<![^\s.\-_*]){_UNIT}(?:[\s.\-_*]{{1,3}}{_UNIT.replace(chr(92) + '1', chr(92) + '2')}){{2,}}(?![^\s.,;:?\-_*\"')\]])")
_MARKS = re.escape("".join(c for c in LOOKS if not c.isalnum()))
EDGE = re.compile(rf"^[^\w{_MARKS}]+|[^\w{_MARKS}]+$")
TWICE = re.compile(r"(.)\1")
#: Letters none of which is doubled, or a run of one character.
RUN = re.compile(rf"(?:([{LETTERS}])(?!\1))+|(.)\2*", re.DOTALL)
#: Costs of a gap in a run: inside a word, between two.
INSIDE_WORD, BETWEEN = 0.3, 0.0


#: Logarithms by first, second and third character: nested lists, which plain Python reads faster than arrays.
Model = list[list[list[float]]]

# --- character language model -------------------------------------------------------------------------------------


def trigram_counts(texts: list[str]) -> np.ndarray:
    """Counts of character triples of the lower-cased texts, each text between edges."""
    points = np.frombuffer("\n\n".join(["", *texts, ""]).lower().encode("utf-32-le", "surrogatepass"), dtype="<u4")
    code = _CODE[np.where(points < len(_CODE), points, 0)]
    return np.bincount(code[:-2] * A * A + code[1:-1] * A + code[2:], minlength=A**3)


def language_model(docs: DataFrame) -> Model:
    """Log probability of the third character after two, over every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(A**3, dtype=np.int64)
        for batch in batches:
            held: list[str] = []
            size = 0
            for text in text_column(batch, "text"):
                held.append(text)
                size += len(text)
                if size > 1_000_000:
                    total += trigram_counts(held)
                    held, size = [], 0
            if held:
                total += trigram_counts(held)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["triple", "n"])

    rows = docs.select("text").mapInArrow(run, "triple long, n long").groupBy("triple").agg(F.sum("n").alias("n")).collect()  # at most A**3
    counts = np.zeros(A**3)
    for r in rows:
        counts[r.triple] = r.n
    cube = counts.reshape(A, A, A)
    single = (cube.sum(axis=(0, 1)) + 0.5) / (cube.sum() + 0.5 * A)
    double = (cube.sum(axis=0) + 20 * single) / (cube.sum(axis=(0, 2))[:, None] + 20)
    return np.log((cube + 20 * double[None]) / (cube.sum(axis=2)[:, :, None] + 20)).tolist()


# --- lattice ------------------------------------------------------------------------------------------------------


def lattice(token: str) -> list[list[tuple[str, float]]]:
    """For each run of one character, or stretch of single letters, what it may stand for, with the channel's cost."""
    out = []
    for run in RUN.finditer(token):
        c, said = run[2], run[0]
        if c is None:
            out.append([(said, 0.0)])
            continue
        n = len(said)
        if c == " ":  # only runs have it
            out.append([("", INSIDE_WORD), (" ", BETWEEN)])
        elif c in _INDEX:
            out.append([(c, 1.0 if n == 2 else 0.2), (c * 2, 0.0 if n == 2 else 0.7)])
        else:
            drop = [("", 2.0)] if not c.isalnum() or n == 1 else []
            looks = [(x * k, 0.7 + 0.5 * (k - 1)) for x in LOOKS.get(c, "") for k in range(1, min(n, 2) + 1)]
            out.append([*looks, *drop] or [("", 3.0)])
    return out


def decode(token: str, lm: Model) -> str:
    """The likeliest word behind ``token``: Viterbi over states of the last two characters."""
    best: dict[tuple[int, int], tuple[float, tuple]] = {(0, 0): (0.0, ())}  # score, and the way back: (earlier, letters)
    for choices in lattice(token):
        after: dict[tuple[int, int], tuple[float, tuple]] = {}
        for (a, b), (score, way) in best.items():
            for letters, cost in choices:
                x, y, s = a, b, score - cost
                for c in letters:
                    z = _INDEX.get(c, 0)  # 0: between words
                    s += lm[x][y][z]
                    x, y = y, z
                if (x, y) not in after or after[x, y][0] < s:
                    after[x, y] = (s, (way, letters))
        best = after
    ends = [ab for ab in best if ab != (0, 0)] or [*best]  # without any letter only if there is no other reading
    way = best[max(ends, key=lambda ab: (best[ab][0] + lm[ab[0]][ab[1]][0], ab))][1]
    parts = []
    while way:
        way, letters = way
        parts.append(letters)
    return "".join(reversed(parts))


def restored(token: str, lm: Model) -> str:
    """A word of plain letters, none doubled, stands for itself; any other with a letter or look-alike goes through the lattice."""
    token = EDGE.sub("", token)
    if not token or token.isalpha() and not TWICE.search(token):
        return token
    if not any(c in _INDEX or c in LOOKS for c in token):
        return ""
    return decode(token, lm)


def parts(text: str) -> set[str]:
    """Tokens of a lower-cased text, and its runs of short tokens, each gap as one blank."""
    found = set(text.split())
    found.update(GAP.sub(" ", m[0]) for m in SPACED.finditer(text))
    return found


def read(part: str, lm: Model) -> list[str]:
    """The words behind a token or a run."""
    return decode(part, lm).split() if " " in part else [w] if (w := restored(part, lm)) else []


def words_of(text: str, lm: Model, known: dict[str, list[str]]) -> set[str]:
    """Restored words of a text, among them those joined from letters set apart."""
    if len(known) > CACHE:
        known.clear()
    out = set()
    for part in parts(text.lower()):
        words = known.get(part)
        if words is None:
            words = known[part] = read(part, lm)
        out.update(words)
    return out


# --- lexicon ------------------------------------------------------------------------------------------------------


def features(word: str) -> tuple[str, ...]:
    """The word as a whole, and its beginnings of four to six letters."""
    n = len(word)
    if n >= 6:
        return word + "$", word[:4], word[:5], word[:6]
    return (word + "$", word[:4], word) if n == 5 else (word + "$", word) if n == 4 else (word + "$",)


def _train_rows(docs: DataFrame, labels: DataFrame, bound: int) -> DataFrame:
    may = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    share = min(1.0, bound / max(may.count(), 1))
    few = may.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) < int(share * (1 << 40)))
    return docs.select("doc_id", "text").join(F.broadcast(few), "doc_id")  # at most about `bound` rows of two numbers


def learn(docs: DataFrame, labels: DataFrame, lm: Model, bound: int = MAX_TRAIN) -> tuple[dict[str, float], float]:
    """Lexicon {feature: probability that a document with it is toxic}, and that of documents without any.

    Features are taken greedily, the surest first, as long as they explain toxic documents not explained yet: words that
    merely come along in copies of a toxic document aren't taken.
    """
    from gleaner.sources.shared import written

    rows = written(_train_rows(docs, labels, bound), "labelled")  # bounded
    shared = docs.sparkSession.sparkContext.broadcast(lm)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, list[str]] = {}
        seen: dict[str, list[int]] = defaultdict(lambda: [0, 0])

        def flush() -> pa.RecordBatch:
            flat = list(seen.items())
            seen.clear()
            return pa.RecordBatch.from_arrays([pa.array([k for k, _ in flat], pa.string()), *(pa.array([v[i] for _, v in flat], pa.int64()) for i in (1, 0))], ["feature", "bad", "good"])

        for batch in batches:
            for text, toxic in zip(text_column(batch, "text"), batch.column("toxic").to_pylist(), strict=True):
                for f in {f for w in words_of(text, shared.value, known) for f in features(w)}:
                    seen[f][int(toxic)] += 1
            if len(seen) > 300_000:
                yield flush()
        yield flush()

    tally = rows.mapInArrow(count, "feature string, bad long, good long").groupBy("feature").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    sure = (F.col("bad") + 0.5) / (F.col("bad") + F.col("good") + 2)
    chosen = tally.where((F.col("bad") >= 3) & (sure >= 0.6)).orderBy(F.desc(F.col("bad") * sure), "feature").limit(MAX_CANDIDATES).collect()
    rate = {r.feature: (r.bad, r.good) for r in chosen}

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, list[str]] = {}
        for batch in batches:
            got, toxic = [], batch.column("toxic").to_pylist()
            for text in text_column(batch, "text"):
                got.append([f for f in {f for w in words_of(text, shared.value, known) for f in features(w)} if f in rate])
            yield pa.RecordBatch.from_arrays([pa.array(toxic, pa.int32()), pa.array(got, pa.list_(pa.string()))], ["toxic", "found"])

    bad_docs = [set(r.found) for r in rows.where("toxic = 1").mapInArrow(own, "toxic int, found array<string>").collect()]  # bounded sample
    holders: dict[str, set[int]] = defaultdict(set)
    for i, found in enumerate(bad_docs):
        for f in found:
            holders[f].add(i)
    open_docs, taken = set(range(len(bad_docs))), []
    while holders and len(taken) < MAX_LEXICON:
        f = max(holders, key=lambda f: (len(holders[f] & open_docs) * (rate[f][0] + 0.5) / (sum(rate[f]) + 2), len(f), f))
        if len(holders[f] & open_docs) < max(3, 0.0005 * len(bad_docs)):
            break
        taken.append(f)
        open_docs -= holders.pop(f)
    # Further features as good as those taken: nearly never in clean documents, and in many toxic ones.
    taken += [f for f in holders if rate[f][0] >= 30 and rate[f][0] >= 200 * rate[f][1] and rate[f][0] >= 0.01 * len(bad_docs)]
    n = rows.count()
    rest = (len(open_docs) + 0.5) / max(1.0, n - len(bad_docs) + len(open_docs) + 1)
    return {f: (rate[f][0] + 0.5) / (sum(rate[f]) + 2) for f in taken}, min(rest, 0.25)


class Scorer:
    """Scores texts; what a token counts is kept, up to a bound."""

    def __init__(self, lm: Model, lexicon: dict[str, float], rest: float) -> None:
        self.lm, self.lexicon, self.rest, self.hits = lm, lexicon, rest, TwoAges(CACHE)

    def weights(self, part: str) -> tuple[tuple[str, float], ...]:
        """The words behind a token or a run that are in the lexicon, and what each counts."""
        lexicon, out = self.lexicon, []
        for word in read(part, self.lm):
            found = [lexicon[f] for f in features(word) if f in lexicon]
            if found:
                out.append((word, max(found)))
        return tuple(out)

    def __call__(self, text: str) -> float:
        """Noisy-or of the words found; ``rest`` without any."""
        found, hits = parts(text.lower()), self.hits
        for part in hits.missing(found):
            hits[part] = self.weights(part)
        miss = 1.0 - self.rest
        for p in sorted(dict(x for part in found for x in hits[part]).values()):
            miss *= 1.0 - p
        return 1.0 - miss


def scorer(model: tuple[Model, dict[str, float], float]) -> Scorer:
    """One for all tasks of a worker process that have the same model."""
    return one(model, lambda: Scorer(*model))


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of ``docs`` (doc_id, text); ``labels``: (doc_id, toxic).

    Null and empty texts score the rate of toxic documents without a lexicon word. Repeated rows each get a row, a null
    doc_id stays null, other columns are not read, an empty table gives an empty one; without labels all score alike.
    """
    lm = language_model(docs)
    lexicon, rest = learn(docs, labels, lm)
    shared = docs.sparkSession.sparkContext.broadcast((lm, lexicon, rest))  # A**3 and MAX_LEXICON numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = scorer(shared.value)
        for batch in batches:
            got = [score(t) for t in text_column(batch, "text")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(got, pa.float64()), pa.array([int(x >= THRESHOLD) for x in got], pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` with all its columns, less the rows predicted toxic.

    Null and empty texts stay; repeated rows stay or go together; a null doc_id changes nothing; other columns may have any
    type or name; without labels all rows stay; an empty table gives an empty one.
    """
    lm = language_model(docs)
    lexicon, rest = learn(docs, labels, lm)
    shared = docs.sparkSession.sparkContext.broadcast((lm, lexicon, rest))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = scorer(shared.value)
        for batch in batches:
            rows = batch.column("row")
            stays = [score(t.as_py() or "") < THRESHOLD for t in rows.field("text")]
            yield pa.RecordBatch.from_arrays([rows.filter(pa.array(stays, pa.bool_()))], ["row"])

    whole = docs.select(F.struct(*named(docs)).alias("row"))  # so that no name stands in the way
    return whole.mapInArrow(run, StructType([StructField("row", docs.schema)])).select("row.*")
