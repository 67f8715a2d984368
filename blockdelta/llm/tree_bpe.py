"""BPE encoding and decoding by tree concatenation.

A text is split into words as the tokenizer's own rule does, and words of everyday scripts take their ids from a table of bounded size.
A long stretch that the rule leaves unsplit is halved until no part is longer than a leaf, and the leaves are encoded side by side
in one call. Going up the tree, a window of tokens around each join is encoded anew and grows until both sides agree exactly: its first token
must be the left part's token at that place, and its last one the right part's. Any two neighbours in the outcome are then
neighbours in the encoding of some part of the text, and a sequence of tokens of which that is true is the encoding of the whole.
Windows stay small, so the characters that are encoded again grow with the number of joins and not with the length of the sides.
A window that reaches both ends is the plain encoding; the result is therefore always that of the whole text.

Cuts and windows lie on whole characters. Only the part that ends the stretch is encoded with the word's end. Special tokens part a
text beforehand; all text beyond everyday scripts goes through the library's own normaliser and splitter.

Defined cases: null text is the empty text, without ids; an empty table gives no rows; each row is encoded by itself.
"""

from __future__ import annotations

import hashlib
import json
import os
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

#: Characters of a leaf, and tokens of the first window on each side.
LEAF, WINDOW = 512, 8
#: Words whose ids are kept, at most, and the longest of them.
KEPT_WORDS, KEPT_LENGTH = 1_000_000, 48

# How the tokenizer of these vocabulary files splits words.
WORD = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\p{White_Space}\p{L}\p{N}]+")
#: Beyond these characters, or with separators that libraries classify differently, the library itself normalises and splits.
UNUSUAL = re.compile("[^\x00-ɏ]|[\x1c-\x1f\x85]")

Ids = tuple[int, ...]


class TreeBPE:
    """Encoder and decoder around one tokenizer file."""

    def __init__(self, path: str, leaf: int = LEAF, window: int = WINDOW):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path) as source:
            parts = json.load(source)
        # Words reach it normalised, and normalising twice is not the same for some letters.
        plain = parts | {"normalizer": None, "truncation": None, "padding": None, "added_tokens": []}
        self.normalised = Tokenizer.from_str(json.dumps(plain))
        # Parts of a word that do not end it.
        self.inner = Tokenizer.from_str(json.dumps(plain | {"model": parts["model"] | {"end_of_word_suffix": None}}))
        suffix = parts["model"].get("end_of_word_suffix") or ""
        vocabulary = self.library.get_vocab(with_added_tokens=True)
        self.tokens: list[str] = [""] * (max(vocabulary.values(), default=-1) + 1)
        for token, i in vocabulary.items():
            self.tokens[i] = token
        # Every character of a token stands for one byte.
        self.bytes_of = [len(t.removesuffix(suffix)) if suffix else len(t) for t in self.tokens]
        self.special = {t.content: i for i, t in self.library.get_added_tokens_decoder().items()}
        self.special_text = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.leaf, self.window, self.plain_decoder = leaf, window, self.library.decoder is None
        self.kept: dict[str, Ids] = {}
        #: Joins, windows that had to grow, and characters that went through the library in trees.
        self.joins = self.widened = self.tree_characters = 0

    def encode(self, text: str) -> np.ndarray:
        out: list[Ids] = []
        for k, stretch in enumerate(self.special_text.split(text) if self.special_text else [text]):
            if k % 2:
                out.append((self.special[stretch],))
            elif stretch:
                usual = UNUSUAL.search(stretch) is None
                # White space is dropped by the splitter, so in usual text folding case is all there is to normalise.
                out += self._words(stretch.lower() if usual else self.library.normalizer.normalize_str(stretch), usual)
        return np.fromiter(chain.from_iterable(out), np.uint32)

    def decode(self, ids: np.ndarray) -> str:
        """As the library's decode(ids, skip_special_tokens=False); without a decoder that is the tokens with blanks between."""
        if not self.plain_decoder:
            return self.library.decode(ids.tolist(), skip_special_tokens=False)
        return " ".join(map(self.tokens.__getitem__, ids.tolist()))

    def _words(self, text: str, usual: bool) -> list[Ids]:
        """The ids of each word."""
        if usual:
            words = WORD.findall(text)
        else:
            words = [text[x:y] for _, (x, y) in self.normalised.pre_tokenizer.pre_tokenize_str(text)]
        kept = self.kept
        ids = list(map(kept.get, words))
        if None in ids:
            missing = list({w for w, i in zip(words, ids) if i is None})
            short = [w for w in missing if len(w) <= self.leaf]
            fresh = {w: tuple(e.ids) for w, e in zip(short, self.normalised.encode_batch(short, add_special_tokens=False))}
            fresh |= {w: tuple(self._tree(w)) for w in missing if len(w) > self.leaf}
            ids = [fresh[w] if i is None else i for w, i in zip(words, ids)]
            if len(kept) < KEPT_WORDS:
                kept.update((w, i) for w, i in fresh.items() if len(w) <= KEPT_LENGTH)
        return ids

    def _tree(self, word: str) -> list[int]:
        cuts = [0, len(word)]
        while max(b - a for a, b in zip(cuts, cuts[1:])) > self.leaf:
            cuts = sorted({*cuts, *((a + b) // 2 for a, b in zip(cuts, cuts[1:]))})
        leaves = [word[a:b] for a, b in zip(cuts, cuts[1:])]
        self.tree_characters += len(word)
        parts = [e.ids for e in self.inner.encode_batch(leaves[:-1], add_special_tokens=False)]
        parts.append(self.normalised.encode(leaves[-1], add_special_tokens=False).ids)
        raw = word.encode()
        ends = [len(word[:c].encode()) for c in cuts[1:]]
        while len(parts) > 1:  # one level of the tree
            last = len(parts) - 1
            parts = [self._join(raw, ends[k], parts[k], parts[k + 1], k + 1 == last) if k < last else parts[k] for k in range(0, len(parts), 2)]
            ends = [*ends[1::2], *([ends[-1]] if len(ends) % 2 else [])]
        return parts[0]

    def _join(self, raw: bytes, at: int, left: list[int], right: list[int], closes: bool) -> list[int]:
        """The encoding of both parts as one; they meet at byte ``at``, and ``closes`` tells that the right one ends the word."""
        self.joins += 1
        size, reach = self.bytes_of, self.window
        i, begin, j, end = len(left), at, 0, at
        while True:
            # A window begins and ends where a token and a character do.
            while i and (len(left) - i < reach or raw[begin] & 0xC0 == 0x80):
                i -= 1
                begin -= size[left[i]]
            while j < len(right) and (j < reach or raw[end] & 0xC0 == 0x80):
                end += size[right[j]]
                j += 1
            text = raw[begin:end].decode()
            self.tree_characters += len(text)
            coder = self.normalised if closes and j == len(right) else self.inner
            middle = coder.encode(text, add_special_tokens=False).ids
            if (not i or middle[0] == left[i]) and (j == len(right) or middle[-1] == right[j - 1]):
                return left[:i] + middle + right[j:]
            self.widened += 1
            reach *= 2


@lru_cache(maxsize=2)
def _coder(path: str, leaf: int, window: int) -> TreeBPE:
    return TreeBPE(path, leaf, window)


def encode_documents(docs: DataFrame, path: str, leaf: int = LEAF, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """Per row: id, n_tokens, ids_sha256, decoded_sha256; with ``keep_ids`` the ids themselves and the decoded text too."""
    schema = "id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<long>, decoded string" if keep_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _coder(path, leaf, window)
        for batch in batches:
            counts, ids_hash, text_hash, all_ids, all_text = [], [], [], [], []
            for text in batch.column(1):
                ids = coder.encode(text.as_py() or "")
                decoded = coder.decode(ids)
                counts.append(len(ids))
                ids_hash.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                text_hash.append(hashlib.sha256(decoded.encode()).hexdigest())
                if keep_ids:
                    all_ids.append(ids.tolist())
                    all_text.append(decoded)
            columns = [batch.column(0), pa.array(counts, pa.int64()), pa.array(ids_hash, pa.string()), pa.array(text_hash, pa.string())]
            if keep_ids:
                columns += [pa.array(all_ids, pa.list_(pa.int64())), pa.array(all_text, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"][: len(columns)])

    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return map_batches(texts, run, schema).withColumnRenamed("id", id_col)
