"""Toxicity by class-conditional Kneser-Ney models of words, spelt letter by letter.

Toxic and ordinary training texts each give a model of the next letter after the last ``ORDER - 1`` ones of a word, its end included.
Absolute discounting takes the same amount off every count of a class; what it frees is spread by shorter contexts, whose counts
are continuation counts (in how many different longer contexts a sequence was seen) that both classes share. So a rare expression gets
nearly the same probability from either model, while one that a class really uses keeps its weight. A text's evidence is the difference
of its two log-likelihoods over its length in words, and the same for its most toxic stretches of ``STRETCHES`` words; a logistic
curve, fitted to training texts scored by models that had not seen them, turns that into a score. All words of a text count, for either class.

Letters are folded to ``SYMBOLS`` symbols (a-z, and the others into five classes by code point), so there are SYMBOLS**ORDER sequences
at any size of the corpus: counts of all labelled training rows are summed map-side, the driver gets at most so many numbers for
each class and fold, and the broadcast table of log ratios is 4 MB.

Inputs of a score are texts alone. Defined cases: null and wordless texts have no evidence and get the score of none; without any
training rows all scores are 0; an empty table gives no rows; a text labelled more than once counts as toxic if any label says so.
"""

from __future__ import annotations

import math
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_batches, staged

#: Letters of a sequence, symbols (0 is a word's edge), and the discount of every count.
ORDER, SYMBOLS, DISCOUNT = 4, 32, 0.75
#: Words of the stretches that are looked at by themselves.
STRETCHES = (1, 4, 16)
#: Folds that are learnt from, and bits of the filter that tells which texts may have a label.
FOLDS, FILTER_BITS = (0, 1, 3), 20
#: Training texts that the logistic curve is fitted to, about.
CALIBRATION_ROWS = 20_000


def fold(id_col: str) -> Column:
    """Remainder 2 marks the rows that nothing is learnt from."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(4))


@lru_cache(maxsize=1)
def _symbol_of() -> np.ndarray:
    """The symbol of each code point: 1-26 for a-z, 27-31 for other letters, 0 for anything else."""
    out = np.zeros(0x110000, np.uint8)
    for point in range(128, 0x110000):
        if unicodedata.category(chr(point))[0] == "L":
            out[point] = 27 + point % 5
    out[ord("a") : ord("z") + 1] = np.arange(1, 27)
    return out


def spelt(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(sequences, first of each word): the number of the last ORDER symbols at every letter and every end of a word."""
    symbols = _symbol_of()[np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), "<u4")]
    letter = symbols > 0
    first = letter & ~np.concatenate([[False], letter[:-1]])
    words = int(first.sum())
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    # Words are laid out with ORDER - 1 edges before each, the first of which is the end of the word before.
    word = (np.cumsum(first) - 1)[letter]
    at = np.arange(len(word)) + (word + 1) * (ORDER - 1)
    laid = np.zeros(len(word) + (words + 1) * (ORDER - 1), np.int64)
    laid[at] = symbols[letter]
    number = np.zeros(len(laid), np.int64)
    for back in range(ORDER):
        number[back:] += laid[: len(laid) - back] * SYMBOLS**back
    begin = np.flatnonzero(first[letter])
    ends = np.append(at[begin[1:] - 1], at[-1]) + 1
    counted = np.sort(np.concatenate([at, ends]))
    return number[counted], begin + np.arange(words)


def evidence(text: str | None, ratios: np.ndarray) -> list[float]:
    """The log-likelihood difference a word, of the whole text and of its most toxic stretches, and the logarithm of its length."""
    sequences, first = spelt(text)
    if not len(first):
        return [0.0] * (len(STRETCHES) + 2)
    total = np.concatenate([[0.0], np.cumsum(np.add.reduceat(ratios[sequences].astype(np.float64), first))])
    out = [total[-1] / len(first)]
    for words in STRETCHES:
        k = min(words, len(first))
        out.append((total[k:] - total[:-k]).max() / words)
    return [*map(float, out), math.log1p(len(first))]


def _sequence_counts(train: DataFrame) -> np.ndarray:
    """Counts by (fold, class, sequence) of the rows (text, toxic, fold), summed in each task and then over all."""
    kinds = 2 * len(FOLDS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((kinds, SYMBOLS**ORDER), np.int64)
        for batch in batches:
            for text, toxic, part in zip(*(batch.column(k) for k in range(3))):
                np.add.at(counts[2 * FOLDS.index(part.as_py()) + toxic.as_py()], spelt(text.as_py())[0], 1)
        kind, sequence = np.nonzero(counts)
        for a in range(0, len(kind), 1 << 16):
            some = slice(a, a + (1 << 16))
            yield pa.RecordBatch.from_arrays([pa.array(kind[some]), pa.array(sequence[some]), pa.array(counts[kind[some], sequence[some]])], names=["kind", "sequence", "n"])

    counted = map_batches(train.select("text", "toxic", "fold"), run, "kind long, sequence long, n long")
    summed = counted.groupBy("kind", "sequence").agg(F.sum("n").alias("n")).toArrow()  # at most kinds * SYMBOLS**ORDER rows
    out = np.zeros((kinds, SYMBOLS**ORDER), np.int64)
    out[summed.column("kind").to_numpy(), summed.column("sequence").to_numpy()] = summed.column("n").to_numpy()
    return out.reshape(len(FOLDS), 2, -1)


def _discounted(counts: np.ndarray, lower: np.ndarray) -> np.ndarray:
    """Probabilities of the last symbol after the others: discounted counts, and the shorter context with what that frees."""
    total, kinds = counts.sum(-1, keepdims=True), (counts > 0).sum(-1, keepdims=True)
    spread = np.broadcast_to(lower, counts.shape)
    return np.where(total > 0, (np.maximum(counts - DISCOUNT, 0) + DISCOUNT * kinds * spread) / np.maximum(total, 1), spread)


def log_ratios(ordinary: np.ndarray, toxic: np.ndarray) -> np.ndarray:
    """The logarithm of toxic over ordinary probability for each sequence, from the classes' counts."""
    classes = [np.asarray(c).reshape((SYMBOLS,) * ORDER) for c in (ordinary, toxic)]
    continuations, level = [], classes[0] + classes[1]
    for _ in range(ORDER - 1):
        level = (level > 0).sum(0)  # different symbols before what is left
        continuations.append(level)
    shared = np.full(SYMBOLS, 1.0 / SYMBOLS)
    for level in reversed(continuations):
        shared = _discounted(level, shared)
    p0, p1 = (_discounted(c, shared) for c in classes)
    return (np.log(p1) - np.log(p0)).astype(np.float32).ravel()


def _fit(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Ridge-damped logistic regression by Newton steps; the last weight is the constant."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w, damp = np.zeros(x.shape[1]), np.diag([0.1] * (x.shape[1] - 1) + [1e-3])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + damp, x.T @ (y - p) - damp @ w)
        w += np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-6:
            break
    return w


class ToxicityModel:
    """Log ratios of sequences and the logistic curve."""

    def __init__(self, ratios: np.ndarray, curve: np.ndarray):
        self.ratios, self.curve = ratios, curve

    def score(self, text: str | None) -> float:
        x = float(np.dot(self.curve[:-1], evidence(text, self.ratios)) + self.curve[-1])
        return 1 / (1 + math.exp(-x)) if x > -700 else 0.0


def _may_have(texts: DataFrame, marks: DataFrame) -> DataFrame:
    """The rows of ``texts`` (id, text) whose id shares a slot with some mark: fewer texts move to their labels, the join decides."""
    slot = F.pmod(F.xxhash64(F.lit(6), F.col("id")), F.lit(1 << FILTER_BITS))
    mask = np.zeros(1 << FILTER_BITS, bool)
    mask[marks.select(F.col("mark_id").alias("id")).select(slot.alias("s")).distinct().toArrow().column(0).to_numpy()] = True  # at most 2**FILTER_BITS numbers
    shared = texts.sparkSession.sparkContext.broadcast(np.packbits(mask))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = np.unpackbits(shared.value).astype(bool)
        for batch in batches:
            kept = batch.filter(pa.array(wanted[batch.column(0).to_numpy()]))
            yield pa.RecordBatch.from_arrays(kept.columns[1:], names=["id", "text"])

    schema = texts.select("id", "text").schema
    return map_batches(texts.select(slot.alias("slot"), "id", "text"), run, schema)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> ToxicityModel:
    """Learns from the labelled rows whose fold is not 2."""
    marks = labels.select(F.col(id_col).alias("mark_id"), F.col(label_col).cast("int").alias("toxic")).where(F.col("toxic").isin(0, 1) & F.col("mark_id").isNotNull())
    marks = marks.where(fold("mark_id") != 2).groupBy("mark_id").agg(F.max("toxic").cast("long").alias("toxic"))
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).where(fold("id") != 2)
    texts = _may_have(texts, marks)
    # The fold is taken again from the id, so that no part of the label's row but the label itself comes along.
    joined = texts.hint("merge").join(marks, F.col("id") == F.col("mark_id"))
    rows = staged(joined.select("id", "text", "toxic", fold("id").cast("long").alias("fold")), "toxicity-train")
    counts = _sequence_counts(rows)
    none = np.array([0.0] * (len(STRETCHES) + 2) + [-1000.0])
    if not counts.any():
        return ToxicityModel(log_ratios(*counts.sum(0)), none)
    without = {f: log_ratios(*(counts.sum(0) - counts[k])) for k, f in enumerate(FOLDS)}
    shared = docs.sparkSession.sparkContext.broadcast(without)
    names = [f"x{k}" for k in range(len(none) - 1)]

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [evidence(text.as_py(), shared.value[part.as_py()]) for text, part in zip(batch.column(0), batch.column(1))]
            yield pa.RecordBatch.from_arrays([*(pa.array([r[k] for r in x], pa.float64()) for k in range(len(names))), batch.column(2)], names=[*names, "y"])

    share = min(1.0, CALIBRATION_ROWS / max(1, rows.count()))
    some = rows.where(F.pmod(F.xxhash64(F.lit(5), "id"), F.lit(1_000_000)) < int(share * 1_000_000)).select("text", "fold", "toxic")
    sample = np.array([list(r) for r in map_batches(some, features, ", ".join(f"{n} double" for n in names) + ", y long").collect()]).reshape(-1, len(names) + 1)
    shared.unpersist()
    return ToxicityModel(log_ratios(*counts.sum(0)), _fit(sample[:, :-1], sample[:, -1]) if len(sample) else none)


def score_documents(docs: DataFrame, model: ToxicityModel, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """All rows and columns of ``docs`` with the score; a column of that name is replaced."""
    docs = docs.drop(score_col)
    shared, at = docs.sparkSession.sparkContext.broadcast((model.ratios, model.curve)), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = ToxicityModel(*shared.value)
        for batch in batches:
            scores = pa.array([own.score(text.as_py()) for text in batch.column(at)], pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, scores], names=[*batch.schema.names, score_col])

    schema = docs.select("*", F.lit(0.0).alias(score_col)).schema
    return map_batches(docs, run, schema)
