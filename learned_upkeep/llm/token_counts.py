"""Operator 3, token counts by a linear longest-match automaton.

The vocabulary is a trie over bytes, plus one symbol for the end of a word.  Each node has a failure
link and the number of tokens that following it completes, so a word's greedy longest-match length
is counted in one pass over its bytes, without building the pieces.  Words repeat, so a worker
remembers the lengths of words it has seen, in a bounded memory.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

from .words import blocks, per_document

WORD_END = 256
MEMORY = 1_000_000
SCHEMA = "doc_id long, n_words long, n_tokens long, n_bytes long"


def vocabulary_pieces(path: str, end: str = "</w>") -> set[tuple[bytes, bool]]:
    """(bytes, ends a word) of the entries of a byte-level vocabulary; every single byte is among them."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    byte_of = {chr(b if b in own else next(rest)): b for b in range(256)}
    found = set()
    with open(path, encoding="utf-8") as f:
        entries = json.load(f)["model"]["vocab"]
    for e in entries:
        stem, last = (e[: -len(end)], True) if e.endswith(end) else (e, False)
        if stem and all(c in byte_of for c in stem):
            found.add((bytes(byte_of[c] for c in stem), last))
    return found | {(bytes([b]), False) for b in range(256)}


class LongestMatch:
    """Greedy longest-match lengths.

    ``goto[v]`` maps a symbol to a child, ``fail[v]`` is where matching goes on when no child fits,
    and ``popped[v]`` counts the tokens that this step completes.  The word's end is consumed by
    itself, as no token, where no entry that ends a word takes it.
    """

    def __init__(self, pieces: set[tuple[bytes, bool]]) -> None:
        self.goto: list[dict[int, int]] = [{}]
        entry = [False]
        for stem, last in pieces:
            v = 0
            for s in (*stem, *([WORD_END] if last else [])):
                if s not in self.goto[v]:
                    self.goto[v][s] = len(self.goto)
                    self.goto.append({})
                    entry.append(False)
                v = self.goto[v][s]
            entry[v] = True
        self.goto[0].setdefault(WORD_END, 0)
        self.fail, self.popped = [-1] * len(self.goto), [0] * len(self.goto)
        level = [(0, s, v) for s, v in self.goto[0].items() if v]
        while level:
            for parent, s, v in level:
                if entry[v]:
                    self.fail[v], self.popped[v] = 0, 1
                    continue
                count, at = self.popped[parent], self.fail[parent]
                while at >= 0 and s not in self.goto[at]:
                    count, at = count + self.popped[at], self.fail[at]
                self.fail[v], self.popped[v] = (self.goto[at][s], count) if at >= 0 else (-1, 0)
            level = [(v, s, w) for _, _, v in level for s, w in self.goto[v].items()]

    def count(self, word: bytes) -> int:
        goto, fail, popped = self.goto, self.fail, self.popped
        n, v = 0, 0
        for s in (*word, WORD_END):
            while (w := goto[v].get(s)) is None:
                n += popped[v]
                v = fail[v]
            v = w
        while v:
            n += popped[v]
            v = fail[v]
        return n


class _Lengths(dict):
    def __init__(self, automaton: LongestMatch) -> None:
        super().__init__()
        self.automaton = automaton

    def __missing__(self, word: bytes) -> int:
        if len(self) >= MEMORY:
            self.clear()
        self[word] = n = self.automaton.count(word)
        return n


@lru_cache(maxsize=2)
def _lengths(vocabulary: str) -> _Lengths:
    """One automaton and memory for all tasks of a worker process."""
    return _Lengths(LongestMatch(vocabulary_pieces(vocabulary)))


def token_counts(docs: DataFrame, vocabulary: str) -> DataFrame:
    """One row per input row: doc_id, n_words, n_tokens, n_bytes.

    Words are runs without ASCII white space, with A-Z lower-cased.  A null or empty text counts 0.
    Repeated rows are counted each; an empty table gives an empty result; further columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lengths = _lengths(vocabulary)
        for batch in blocks(batches):
            rows = []
            for text in batch.column("text").cast(pa.binary()).to_pylist():
                words = (text or b"").lower().split()
                rows.append((len(words), sum(map(lengths.__getitem__, words)), len(text or b"")))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(c, pa.int64()) for c in zip(*rows, strict=True)]], ["doc_id", "n_words", "n_tokens", "n_bytes"])

    return per_document(docs, run, SCHEMA)
