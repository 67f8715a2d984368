"""Secrets in texts: three fixed patterns, and strings that pass a battery of randomness tests.

Long runs of encoding characters are candidates, be they letters, digits or both. The smallest encoding that holds all characters
of a run is its alphabet; under even draws from it a chi-squared test over cells of the alphabet, a runs test about the
middle of the alphabet and a lag-one serial correlation give three p-values, combined by Fisher's method.

How often ordinary text looks that random depends on length and alphabet, so the corpus itself says it: all words of all texts are
strung together without the spaces between, in turns of five kinds (as written, in lower case, with the words' lengths or hyphens
between) and of each length class, each word in one string; all digits likewise. A candidate's false-discovery p-value is the part of these ordinary strings
of its kind and length class that look at least as random; the step-up rule at level ``q`` over all candidates of the corpus then
bounds the expected part of ordinary strings among what is reported as ``random``. On short runs of letters ordinary words look as
random as keys, so such a run is not reported; long ones are told apart.

Candidates and ordinary strings are counted by kind, length class and p-value step; a fixed number of rows comes to the driver and
the cuts go back as constants.

Defined cases: null text is the empty text, without spans; an empty table gives no rows; spans are in code points, end
exclusive; a candidate that lies within a pattern's span is none; rows repeated under one id are scanned each; a corpus without
ordinary strings of a kind reports none of it. ``redact`` passes all columns through.
"""

from __future__ import annotations

import math
import re
import zlib
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_batches, staged

# The three patterns asked for, and the least lengths of what they match.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
KEYWORDS = ("password", "passwd", "secret", "token", "key")
LEAST_ASSIGN, LEAST_ACCESS, LEAST_HEX = 6, 20, 24
KINDS = ("assign", "access", "hex", "random")

CANDIDATE = re.compile(r"[A-Za-z0-9+/_-]{20,}={0,2}")
#: First length of each length class; ordinary strings of a class have this length.
LENGTH_CLASSES = (20, 28, 40, 64, 128)
#: p-values are counted in steps of this part of a power of ten, down to 10**-10.
STEPS_PER_DECADE, STEPS = 20, 200
LEAST_BITS, LEAST_EXPECTED = 80, 3
#: What ordinary strings are made of; longer ones may be keys themselves.
ORDINARY_WORD = re.compile(r"(?<![A-Za-z0-9])[A-Za-z]{1,19}(?![A-Za-z0-9])")

_DIGITS, _LOWER, _UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Kinds of ordinary strings.
NULLS = ("lower", "letters", "digits", "lower and digits", "letters and digits", "slug")
#: What a word gives to a string of each kind, from its place in the string; digits are taken without words.
FORMS = {
    0: lambda place, word: word.lower(),
    1: lambda place, word: word,
    3: lambda place, word: f"{word.lower()}{len(word)}",
    4: lambda place, word: f"{word}{len(word)}",
    5: lambda place, word: f"{word}{len(word)}-" if place % 3 == 2 else f"{word}-",
}
#: Kinds and length classes in the order in which a text's words fill them.
TURNS = [(kind, k) for kind in FORMS for k in range(len(LENGTH_CLASSES))]
DIGIT_RUN = re.compile("[0-9]+")


class Alphabet:
    """Symbols in order, and cells of neighbouring symbols; no cell crosses from digits to letters or from one case to the other."""

    def __init__(self, null: str, *classes: str):
        symbols = "".join(classes)
        self.null, self.classes = NULLS.index(null), classes
        self.index = {c: i for i, c in enumerate(symbols)}
        self.bits = math.log2(len(symbols))
        self.middle, self.size = (len(symbols) - 1) / 2, len(symbols)
        self.mean, self.var = self.middle, (len(symbols) ** 2 - 1) / 12

    @lru_cache(maxsize=1024)
    def cells(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """(cell of each symbol, share of each cell): as many as leave at least ``LEAST_EXPECTED`` of ``n`` symbols to each."""
        cell, share = [], []
        for part in self.classes:
            parts = max(1, min(len(part), int(n * len(part) / self.size / LEAST_EXPECTED)))
            for k in range(parts):
                own = part[len(part) * k // parts : len(part) * (k + 1) // parts]
                cell += [len(share)] * len(own)
                share.append(len(own) / self.size)
        return np.array(cell), np.array(share)

    def numbers(self, token: str) -> list[int]:
        return [self.index[c] for c in token]


#: From the narrowest to the widest.
ALPHABETS = (
    Alphabet("digits", _DIGITS),
    Alphabet("lower and digits", _DIGITS, "abcdef"),
    Alphabet("lower and digits", _DIGITS, "ABCDEF"),
    Alphabet("lower", _LOWER),
    Alphabet("lower", _UPPER),
    Alphabet("lower and digits", "234567", _UPPER),
    Alphabet("lower and digits", _DIGITS, _LOWER),
    Alphabet("lower and digits", _DIGITS, _UPPER),
    Alphabet("letters", _LOWER, _UPPER),
    Alphabet("letters and digits", _DIGITS, _LOWER, _UPPER),
    Alphabet("slug", _DIGITS, _LOWER, _UPPER, "+/"),
    Alphabet("slug", _DIGITS, _LOWER, _UPPER, "-_"),
    Alphabet("slug", _DIGITS, _LOWER, _UPPER, "+/-_"),
)


def alphabet_of(body: str) -> Alphabet:
    kinds = set(body)
    return next(a for a in ALPHABETS if kinds <= a.index.keys())


_erfc = np.frompyfunc(math.erfc, 1, 1)


def two_sided(z: np.ndarray) -> np.ndarray:
    return _erfc(np.abs(z) / math.sqrt(2)).astype(np.float64)


def chi2_tail(x: np.ndarray, df: int) -> np.ndarray:
    """Upper tail by the cube-root normal approximation."""
    z = ((np.maximum(x, 0) / df) ** (1 / 3) - (1 - 2 / (9 * df))) / math.sqrt(2 / (9 * df))
    return np.where(x > 0, 0.5 * _erfc(z / math.sqrt(2)).astype(np.float64), 1.0)


def battery(at: np.ndarray, alphabet: Alphabet) -> np.ndarray:
    """Combined p-value of each row of symbol numbers, under even draws from the alphabet."""
    n = at.shape[1]
    cell, share = alphabet.cells(n)
    cells, expected = cell[at], n * share
    observed = np.stack([(cells == k).sum(1) for k in range(len(expected))], 1)
    even = chi2_tail(((observed - expected) ** 2 / expected).sum(1), max(1, len(expected) - 1))
    high = at > alphabet.middle
    up = high.sum(1)
    runs, mean = 1 + (high[:, 1:] != high[:, :-1]).sum(1), 1 + 2 * up * (n - up) / n
    spread = (mean - 1) * (mean - 2) / (n - 1)
    run_p = np.where(spread > 0, two_sided((runs - mean) / np.sqrt(np.maximum(spread, 1e-9))), 1.0)
    run_p = np.where((up == 0) | (up == n), 2.0 ** (1 - n), run_p)
    off = at - alphabet.mean
    serial = (off[:, 1:] * off[:, :-1]).sum(1) / (alphabet.var * math.sqrt(n - 1))
    half = -sum(np.log(np.maximum(p, 1e-300)) for p in (even, run_p, two_sided(serial)))
    return np.exp(-half) * (1 + half + half * half / 2)


def randomness(token: str) -> tuple[float, float]:
    """(combined p-value under even draws from the inferred alphabet, bits that the token could hold)."""
    body = token.rstrip("=")
    alphabet = alphabet_of(body)
    return float(battery(np.array([alphabet.numbers(body)]), alphabet)[0]), alphabet.bits * len(body)


def ordinary_strings(text: str) -> Iterator[tuple[int, int, str]]:
    """(kind, length class, characters): every ordinary word and every digit of the text goes into one string.

    Kinds and length classes take turns from a beginning that the text's checksum gives, so short texts do not all begin
    alike; what is left at the end makes a string of the longest class that it fills.
    """
    turn = zlib.crc32(text.encode("utf-8", "surrogatepass"))
    held, size, place, wanted = [], 0, 0, 0
    for word in ORDINARY_WORD.findall(text):
        if not held:
            kind, wanted = TURNS[turn % len(TURNS)]
        piece = FORMS[kind](place, word)
        held.append(piece)
        size, place = size + len(piece), place + 1
        if size >= LENGTH_CLASSES[wanted]:
            yield kind, wanted, "".join(held)[: LENGTH_CLASSES[wanted]]
            held, size, place, turn = [], 0, 0, turn + 1
    if size >= LENGTH_CLASSES[0]:
        k = bisect_right(LENGTH_CLASSES, size) - 1
        yield kind, k, "".join(held)[: LENGTH_CLASSES[k]]
    digits, at = "".join(DIGIT_RUN.findall(text)), 0
    while len(digits) - at >= LENGTH_CLASSES[0]:
        k = min(turn % len(LENGTH_CLASSES), bisect_right(LENGTH_CLASSES, len(digits) - at) - 1)
        yield 2, k, digits[at : at + LENGTH_CLASSES[k]]
        at, turn = at + LENGTH_CLASSES[k], turn + 1


#: The alphabet that ordinary strings of each kind are tested under.
NULL_ALPHABETS = tuple(alphabet_of(s) for s in (_LOWER, _LOWER + _UPPER, _DIGITS, _DIGITS + _LOWER, _DIGITS + _LOWER + _UPPER, _DIGITS + _LOWER + _UPPER + "-_"))


def ordinary_counts(texts: list[str]) -> Counter:
    """How many ordinary strings there are of each (kind, length class, p-value step)."""
    held: dict[tuple[int, int], list[list[int]]] = {}
    for text in texts:
        for kind, k, characters in ordinary_strings(text):
            held.setdefault((kind, k), []).append(NULL_ALPHABETS[kind].numbers(characters))
    out: Counter = Counter()
    for (kind, k), rows in held.items():
        for a in range(0, len(rows), 4096):
            steps, n = np.unique(p_steps(battery(np.array(rows[a : a + 4096]), NULL_ALPHABETS[kind])), return_counts=True)
            for step, count in zip(steps.tolist(), n.tolist()):
                out[kind, k, step] += count
    return out


def p_steps(p: np.ndarray) -> np.ndarray:
    """Steps count from 0 (p near 1) to STEPS (the smallest)."""
    return np.minimum(STEPS, (-np.log10(np.maximum(p, 1e-300)) * STEPS_PER_DECADE).astype(int))


def scan(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int, int, int]]]:
    """Base spans (start, kind, end) in order, and candidates (start, end, null kind, length class, p-value step) that no base span covers."""
    base: list[tuple[int, int, int]] = []
    lowered = text.lower()
    if any(word in lowered for word in KEYWORDS):
        base += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_ASSIGN]
    if "AKIA" in text:
        base += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    runs = list(CANDIDATE.finditer(text))
    for run in runs:  # a stretch of hexadecimal digits that is long enough lies within such a run
        base += [(m.start(), 2, m.end()) for m in HEX.finditer(text, run.start(), run.end()) if m.end() - m.start() >= LEAST_HEX]
    base.sort()
    found, k = [], 0
    near: list[tuple[int, int, int]] = []
    for run in runs:
        begin, end = run.span()
        near = [s for s in near if s[2] > begin]
        while k < len(base) and base[k][0] < end:
            near += [base[k]] if base[k][2] > begin else []
            k += 1
        at, pieces = begin, []
        for start, _, stop in near:
            pieces.append((at, start))
            at = max(at, stop)
        pieces.append((at, end))
        if all(b - a <= 2 and not text[a:b].strip("=") for a, b in pieces if a < b):
            continue  # covered
        # What base spans leave of a run is tested by itself if it is long enough for that, else the run as a whole.
        for a, b in [(a, b) for a, b in pieces if len(text[a:b].rstrip("=")) >= LENGTH_CLASSES[0]] or [(begin, end)]:
            p, bits = randomness(text[a:b])
            if bits >= LEAST_BITS:
                body = text[a:b].rstrip("=")
                found.append((a, b, alphabet_of(body).null, bisect_right(LENGTH_CLASSES, len(body)) - 1, int(p_steps(np.array(p)))))
    return base, found


_SPAN = pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())])
_FOUND = ("start", "end", "null_kind", "length_class", "step")
_CANDIDATE = pa.struct([(name, pa.int32()) for name in _FOUND])
_COUNTED = ("null_kind", "length_class", "step", "n")
_ORDINARY = pa.struct([(name, pa.int64()) for name in _COUNTED])


def scanned(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, base and candidates per row; the counts of ordinary strings of a batch of rows come with its first one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            texts = [text.as_py() or "" for text in batch.column(1)]
            both = [scan(text) for text in texts]
            base = pa.array([[dict(zip(("start", "kind", "end"), s)) for s in b] for b, _ in both], pa.list_(_SPAN))
            found = pa.array([[dict(zip(_FOUND, s)) for s in c] for _, c in both], pa.list_(_CANDIDATE))
            counted = [dict(zip(_COUNTED, (*key, n))) for key, n in ordinary_counts(texts).items()]
            ordinary = pa.array([counted] + [[]] * (len(texts) - 1), pa.list_(_ORDINARY))
            yield pa.RecordBatch.from_arrays([batch.column(0), base, found, ordinary], names=["id", "base", "candidates", "ordinary"])

    structs = [f"array<struct<{','.join(f'{n}:{t}' for n in names)}>>" for names, t in ((_FOUND, "int"), (_COUNTED, "bigint"))]
    schema = f"id long, base array<struct<start:int,kind:int,end:int>>, candidates {structs[0]}, ordinary {structs[1]}"
    return map_batches(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")), run, schema)


Cell = tuple[int, int, int]


def step_up(candidates: dict[Cell, int], ordinary: dict[Cell, int], q: float) -> dict[tuple[int, int], int]:
    """For each (null kind, length class) the last step that is still reported, by the step-up rule at level ``q`` over all candidates."""
    totals: Counter = Counter()
    for (kind, k, _), n in ordinary.items():
        totals[kind, k] += n
    p = {cell: (1 + sum(ordinary.get((cell[0], cell[1], step), 0) for step in range(cell[2] + 1))) / (1 + totals[cell[0], cell[1]]) for cell in candidates}
    total, rank, limit = sum(candidates.values()), 0, 0.0
    for cell in sorted(p, key=p.get):
        rank += candidates[cell]
        if p[cell] <= q * rank / total:
            limit = p[cell]
    cuts: dict[tuple[int, int], int] = {}
    for (kind, k, step), value in p.items():
        if value <= limit:
            cuts[kind, k] = max(step, cuts.get((kind, k), 0))
    return cuts


def step_cuts(found: DataFrame, q: float) -> dict[tuple[int, int], int]:
    """The cuts from counts over all rows of ``found``; kinds, classes and steps bound what the driver gets."""

    def counted(column: str, n: Column) -> dict[Cell, int]:
        rows = found.select(F.explode(column).alias("c")).groupBy("c.null_kind", "c.length_class", "c.step").agg(F.sum(n).alias("n")).collect()
        return {(r["null_kind"], r["length_class"], r["step"]): r["n"] for r in rows}

    return step_up(counted("candidates", F.lit(1)), counted("ordinary", F.col("c.n")), q)


def _survives(cuts: dict[tuple[int, int], int]) -> Column:
    def test(c: Column) -> Column:
        out = F.lit(False)
        for (kind, k), cut in cuts.items():
            out = out | ((c["null_kind"] == kind) & (c["length_class"] == k) & (c["step"] <= cut))
        return out

    return F.filter("candidates", test)


def find_secrets(docs: DataFrame, q: float = 0.05, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id and ``base`` and ``spans``, arrays of (start, kind, end) by start and kind; kinds are numbered as in KINDS."""
    found = staged(scanned(docs, id_col, text_col), "secret-scan")
    random = F.transform(_survives(step_cuts(found, q)), lambda c: F.struct(c["start"].alias("start"), F.lit(3).alias("kind"), c["end"].alias("end")))
    return found.select(F.col("id").alias(id_col), "base", F.array_sort(F.concat("base", random)).alias("spans"))


def as_text(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def digest(found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Counts, checksum and text of the spans."""
    def of(kind: int) -> Column:
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long")

    return found.select(id_col, of(0).alias("n_assign"), of(1).alias("n_access"), of(2).alias("n_hex"), F.sha2(as_text(F.col("base")), 256).alias("base_sha256"), as_text(F.col("spans")).alias("spans"))


def redact(docs: DataFrame, q: float = 0.05, text_col: str = "text", chars_col: str | None = "n_chars") -> DataFrame:
    """All rows and columns of ``docs``; each secret's characters give way to ``[secret]``, and the count of characters follows."""
    if not docs.columns or text_col not in docs.columns:
        raise ValueError(f"no column {text_col}")
    cuts = step_cuts(staged(scanned(docs.select(F.lit(0).alias("id"), text_col), "id", text_col), "secret-scan"), q)
    at = docs.columns.index(text_col)
    count_at = docs.columns.index(chars_col) if chars_col in docs.columns else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).to_pylist()
            changed = False
            for k, text in enumerate(texts):
                base, found = scan(text or "")
                spans = sorted([(s, e) for s, _, e in base] + [(s, e) for s, e, kind, k, step in found if step <= cuts.get((kind, k), -1)])
                if spans:
                    changed, texts[k] = True, _masked(text, spans)
            if changed:
                columns = list(batch.columns)
                if count_at is not None:
                    old, counts = batch.column(at), batch.column(count_at).to_pylist()
                    new = [len(t) if t is not None and t != o.as_py() else c for t, o, c in zip(texts, old, counts)]
                    columns[count_at] = pa.array(new, batch.schema.field(count_at).type)
                columns[at] = pa.array(texts, batch.schema.field(at).type)
                batch = pa.RecordBatch.from_arrays(columns, schema=batch.schema)
            yield batch

    return map_batches(docs, run, docs.schema)


def _masked(text: str, spans: list[tuple[int, int]]) -> str:
    out, at = [], 0
    for start, end in spans:
        if start >= at:
            out += [text[at:start], "[secret]"]
        at = max(at, end)
    return "".join([*out, text[at:]])
