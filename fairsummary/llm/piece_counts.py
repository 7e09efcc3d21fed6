"""Greedy longest-match token counts in linear time, without building the pieces.

A trie over the vocabulary has, for each node, a failure node (what is left
after the longest matches are taken off its string) and the number of pieces
so taken.  Walking a word follows each character once and adds those numbers.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import WORD_BYTES, Memory, extended, text_slices, texts_of
from .token_table import split_words, vocabulary

HEAD = "▁"
_memories: dict[str, Memory] = {}


class Automaton:
    """Counts for words given with the word-start mark in front; a word that cannot be cut counts as one unknown."""

    def __init__(self, pieces: Iterable[str]):
        self.go: list[dict[str, int]] = [{}]
        whole = [False]
        for piece in pieces:
            node = 0
            for c in piece:
                nxt = self.go[node].get(c)
                if nxt is None:
                    nxt = self.go[node][c] = len(self.go)
                    self.go.append({})
                    whole.append(False)
                node = nxt
            whole[node] = node > 0
        self.fail, self.popped = [-1] * len(self.go), [0] * len(self.go)
        queue = deque([0])
        while queue:
            parent = queue.popleft()
            for c, node in self.go[parent].items():
                queue.append(node)
                if whole[node]:
                    self.fail[node], self.popped[node] = 0, 1
                elif parent:
                    z, n = self.fail[parent], self.popped[parent]
                    while z >= 0 and c not in self.go[z]:
                        n += self.popped[z]
                        z = self.fail[z]
                    if z >= 0:
                        self.fail[node], self.popped[node] = self.go[z][c], n

    def count(self, word: str) -> int:
        """Number of pieces, or -1 where greedy matching gets stuck."""
        go, fail, popped = self.go, self.fail, self.popped
        node = n = 0
        for c in word:
            while c not in go[node]:
                n += popped[node]
                node = fail[node]
                if node < 0:
                    return -1
            node = go[node][c]
        while node:
            n += popped[node]
            node = fail[node]
            if node < 0:
                return -1
        return n


def model_pieces(path: str) -> list[str]:
    """Ordinary pieces of a sentencepiece model: not control, unknown or byte pieces."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    return [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]


def counts_of(path: str) -> Memory:
    """This process's counts for words of a vocabulary; white space counts nothing."""
    if path not in _memories:
        auto = Automaton(model_pieces(path))
        _memories[path] = Memory(lambda words: [auto.count(HEAD + w) if w else 0 for w in words])
    return _memories[path]


def count_pieces(docs: DataFrame, *, text_col: str = "text", vocab: str | None = None) -> DataFrame:
    """Adds ``n_words``, ``n_tokens`` and ``n_unknown`` (words that count as one unknown token).

    Words lie between ASCII white space.  Null and empty texts count zero.
    Columns named like the added ones are replaced.
    """
    vocab = vocab or vocabulary("piece_bpe_32k.model")
    base = docs.drop("n_words", "n_tokens", "n_unknown")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memory = counts_of(vocab)
        for batch in batches:
            for b in text_slices(batch, text_col, WORD_BYTES):
                split = [split_words(t) for t in texts_of(b, text_col)]
                known = memory(set().union(*split))
                out = []
                for s in split:
                    n = np.fromiter(map(known.__getitem__, s), np.int64, len(s))
                    out.append((int(np.count_nonzero(n)), int(np.abs(n).sum()), int(np.count_nonzero(n < 0))))
                yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(c, pa.int64()) for c in zip(*out))], [*b.schema.names, "n_words", "n_tokens", "n_unknown"])

    return base.mapInArrow(run, extended(base.schema, "n_words long, n_tokens long, n_unknown long"))


def digest(docs: DataFrame) -> DataFrame:
    """doc_id and the three counts of every document."""
    return count_pieces(docs.select("doc_id", "text")).drop("text")


def brute_force(text: str | None, pieces: set[str]) -> tuple[int, int, int]:
    """Greedy longest match by trying every length."""
    longest = max(map(len, pieces))
    words = [w for w in split_words(text or "") if w]
    tokens = unknown = 0
    for w in words:
        s, at, n = HEAD + w, 0, 0
        while at < len(s):
            size = next((k for k in range(min(longest, len(s) - at), 0, -1) if s[at : at + k] in pieces), 0)
            if not size:
                break
            at, n = at + size, n + 1
        unknown += at < len(s)
        tokens += n if at == len(s) else 1
    return len(words), tokens, unknown
