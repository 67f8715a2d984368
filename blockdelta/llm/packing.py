"""Packing documents into fixed token windows by minimum bin slack.

Every text is tokenised once, closed by an end id and cut into full windows and one remainder. What is left to do
depends on lengths alone, and there are fewer of these than a window has tokens: their histogram, and nothing else, comes to the
driver. There a bitset subset-sum dynamic program picks, for the longest length left, the multiset of remaining
lengths that fills the window closest to its capacity; backtracking gives the count of each length, and the same
filling is repeated as often as the counts allow. Each piece is numbered among the pieces of its length; number and
length give window and offset by one binary search in the list of fillings.

Defined cases: null text is the empty text, which is the end id alone; an empty table gives no rows; rows repeated
under one id are packed each; windows that stay short hold one filling each and are the only padding.
"""

from __future__ import annotations

import base64
import os
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_batches, staged

#: Fixed value: the special token of the byte-level vocabulary.
END_OF_TEXT = "<|endoftext|>"
#: Slices into which the numbering of all pieces is cut, at most, besides one for each length.
SLICES = 16384
#: tiktoken's splitter goes back over runs of white space and stops the task at some hundred thousand characters; from here on
#: the tokenizers library, which has no such limit, encodes the whole text.
LONG_SPACE = re.compile(r"\s{1000}")


@lru_cache(maxsize=2)
def _encoding(ranks_path: str, pattern: str):
    import tiktoken

    with open(ranks_path, "rb") as lines:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
    return tiktoken.Encoding("byte-bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={END_OF_TEXT: len(ranks)})


@lru_cache(maxsize=2)
def _library(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(path)
    library.no_truncation()
    library.no_padding()
    return library


def token_ids(text: str, ranks_path: str, pattern: str, library_path: str) -> list[int]:
    """The ids that the tokenizers library gives for the file ``library_path``, its special token included; ``ranks_path`` holds the same vocabulary."""
    if LONG_SPACE.search(text):
        return _library(library_path).encode(text, add_special_tokens=False).ids
    encoding = _encoding(ranks_path, pattern)
    if END_OF_TEXT in text:
        return encoding.encode(text, allowed_special={END_OF_TEXT})
    return encoding.encode_ordinary(text)


def pieces_of(docs: DataFrame, ranks_path: str, pattern: str, library_path: str, capacity: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """id, start, length, ids_crc32, doc_tokens of every piece; the texts are read once and ids are not kept."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[list[int]] = [[], [], [], [], []]
            for k, text in enumerate(batch.column(1)):
                ids = token_ids(text.as_py() or "", ranks_path, pattern, library_path)
                ids.append(end_id)
                raw, total = memoryview(np.array(ids, dtype="<u4").tobytes()), len(ids)
                for start in range(0, total, capacity):
                    length = min(capacity, total - start)
                    for values, value in zip(rows, (k, start, length, zlib.crc32(raw[4 * start : 4 * (start + length)]), total)):
                        values.append(value)
            numbers = [pa.array(values, pa.int64()) for values in rows]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(numbers[0]), *numbers[1:]], names=["id", "start", "length", "ids_crc32", "doc_tokens"])

    return map_batches(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")), cut, "id long, start long, length long, ids_crc32 long, doc_tokens long")


@dataclass(frozen=True)
class Filling:
    """One multiset of lengths, used for ``times`` windows."""

    lengths: tuple[tuple[int, int], ...]
    times: int


def closest_multiset(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """The multiset out of ``counts`` whose sum is the largest possible up to ``capacity``.

    Bit t of the set is on if some multiset sums to t. A length with k copies at hand enters in 1, 2, 4, .. copies,
    so each number of copies can be reached.
    """
    reach, mask, stages = 1, (1 << (capacity + 1)) - 1, []
    for length in sorted(counts, reverse=True):
        left, part = min(counts[length], capacity // length), 1
        while left > 0:
            take = min(part, left)
            stages.append((reach, length, take))
            reach |= (reach << (length * take)) & mask
            left -= take
            part *= 2
        if reach >> capacity & 1:
            break
    at, used = reach.bit_length() - 1, {}
    for before, length, take in reversed(stages):
        if not before >> at & 1:
            used[length] = used.get(length, 0) + take
            at -= length * take
    return used


def fill_windows(counts: dict[int, int], capacity: int) -> list[Filling]:
    """Fillings that use up all lengths; the work depends on the number of different lengths, not on their counts."""
    left, out = {length: n for length, n in counts.items() if n}, []
    while left:
        longest = max(left)
        left[longest] -= 1
        used = closest_multiset({length: n for length, n in left.items() if n and length <= capacity - longest}, capacity - longest)
        left[longest] += 1
        used[longest] = used.get(longest, 0) + 1
        times = min(left[length] // n for length, n in used.items())
        for length, n in used.items():
            left[length] -= n * times
            if not left[length]:
                del left[length]
        out.append(Filling(tuple(sorted(used.items(), reverse=True)), times))
    return out


def lay_out(fillings: list[Filling]) -> np.ndarray:
    """Rows (length, first number, copies in a window, first window, offset of the first copy), by length and number."""
    rows, numbered, window = [], {}, 0
    for f in fillings:
        offset = 0
        for length, copies in f.lengths:
            first = numbered.get(length, 0)
            rows.append((length, first, copies, window, offset))
            numbered[length] = first + copies * f.times
            offset += length * copies
        window += f.times
    return np.array(sorted(rows), dtype=np.int64).reshape(-1, 5)


def place(pieces: DataFrame, capacity: int) -> DataFrame:
    """``pieces`` with sequence_id and offset."""
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    plan = lay_out(fill_windows(counts, capacity))
    unit = max(256, -(-sum(counts.values()) // SLICES))
    spark = pieces.sparkSession
    slices = spark.createDataFrame([(length, -(-n // unit)) for length, n in counts.items()] or [(0, 1)], "l long, slices long")
    # A frequent length is numbered by many tasks: slice by slice, each from the running sum of the slices before.
    sliced = pieces.join(F.broadcast(slices), F.col("length") == F.col("l")).withColumn("slice", F.pmod(F.xxhash64("id", "start"), "slices"))
    sizes = sliced.groupBy("length", "slice").agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(Window.partitionBy("length").orderBy("slice").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
    begin = sizes.select(F.col("length").alias("l2"), F.col("slice").alias("s2"), before.alias("begin"))
    number = F.row_number().over(Window.partitionBy("length", "slice").orderBy("id", "start", "ids_crc32")) - 1
    numbered = sliced.withColumn("number", number).join(F.broadcast(begin), (F.col("length") == F.col("l2")) & (F.col("slice") == F.col("s2")))
    numbered = numbered.select("id", "start", "length", "ids_crc32", "doc_tokens", (F.col("number") + F.col("begin")).alias("number"))

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = 1 << 50
        keys = plan[:, 0] * top + plan[:, 1]
        for batch in batches:
            length, number = (batch.column(c).to_numpy() for c in ("length", "number"))
            row = plan[np.searchsorted(keys, length * top + number, side="right") - 1]
            within = number - row[:, 1]
            sequence, offset = row[:, 3] + within // row[:, 2], row[:, 4] + within % row[:, 2] * length
            kept = [batch.column(c) for c in range(5)]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(sequence), pa.array(offset)], names=[*batch.schema.names[:5], "sequence_id", "offset"])

    return map_batches(numbered, look_up, "id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")


def pack(docs: DataFrame, ranks_path: str, pattern: str, library_path: str, capacity: int = 2048, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    pieces = staged(pieces_of(docs, ranks_path, pattern, library_path, capacity, end_id, id_col, text_col), "packing-pieces")
    return place(pieces, capacity).withColumnRenamed("id", id_col)
