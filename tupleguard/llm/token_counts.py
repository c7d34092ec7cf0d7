"""Word-piece token counts by a linear longest-match automaton.

The vocabulary's pieces form a byte trie. Every node has a failure link: the node reached when
the pieces that greedy longest-match-first would emit so far are popped, together with how
many pieces those are, computed once in breadth-first order. A word is then read byte by byte
with no backtracking; counts of popped pieces are added and no piece is ever built, so the
work is linear in the word's length, for any length.

Words are runs of bytes other than ASCII white space, A-Z lowered. ``initial`` pieces may start
a word and ``continuing`` ones follow; where both are one set, one trie serves. A word that the
pieces cannot cover is one unknown token.

Defined cases: null, empty and blank texts have no words and no tokens; repeated rows count
alike; null ids are allowed; other columns are ignored; an empty table gives no rows; an empty
vocabulary makes every word unknown.
"""

from __future__ import annotations

import json

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textkit as tk

#: Words whose counts a task remembers.
MEMO = 400_000
_UNKNOWN = 1 << 40
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


class LongestMatchAutomaton:
    def __init__(self, initial: set[bytes], continuing: set[bytes] | None = None):
        shared = continuing is None or continuing == initial
        self.go: list[dict[int, int]] = [{}]
        final = [False]
        self.root = 0
        self.mid = 0 if shared else self._node(final)
        for start, pieces in ((self.root, initial),) if shared else ((self.root, initial), (self.mid, continuing)):
            for piece in pieces:
                if not piece:
                    continue
                at = start
                for c in piece:
                    nxt = self.go[at].get(c)
                    if nxt is None:
                        nxt = self.go[at][c] = self._node(final)
                    at = nxt
                final[at] = True
        n = len(self.go)
        self.fail, self.popped = [-1] * n, [0] * n
        level = [(self.root, -1, 0)] + ([] if shared else [(self.mid, -1, 0)])
        while level:
            below = []
            for node, parent, c in level:
                if parent >= 0:
                    if final[node]:
                        self.fail[node], self.popped[node] = self.mid, 1
                    else:
                        z, count = self.fail[parent], self.popped[parent]
                        while z >= 0 and c not in self.go[z]:
                            count += self.popped[z]
                            z = self.fail[z]
                        if z >= 0:
                            self.fail[node], self.popped[node] = self.go[z][c], count
                below.extend((child, node, ch) for ch, child in self.go[node].items())
            level = below

    def _node(self, final: list) -> int:
        self.go.append({})
        final.append(False)
        return len(self.go) - 1

    def count(self, word: bytes) -> int:
        """Pieces of the word, or -1 if it is unknown."""
        go, fail, popped = self.go, self.fail, self.popped
        at, total = self.root, 0
        for c in word:
            nxt = go[at].get(c)
            while nxt is None:
                total += popped[at]
                at = fail[at]
                if at < 0:
                    return -1
                nxt = go[at].get(c)
            at = nxt
        while at != self.mid:
            total += popped[at]
            at = fail[at]
            if at < 0:
                return -1
        return total


class _Memo(dict):
    def __init__(self, automaton: LongestMatchAutomaton):
        super().__init__()
        self.automaton = automaton

    def __missing__(self, word: bytes) -> int:
        n = self.automaton.count(word)
        n = 1 + _UNKNOWN if n < 0 else n
        if len(self) >= MEMO:
            self.clear()
        if len(word) <= 64:
            self[word] = n
        return n


def _byte_of() -> dict[str, int]:
    """The byte that each character of a byte-level vocabulary stands for: printable Latin-1
    stands for itself, the other bytes follow from code point 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


def load_pieces(path: str) -> set[bytes]:
    """The pieces of a byte-level vocabulary file of ``tokenizers``; a word-end mark is dropped,
    so that every piece may stand anywhere in a word."""
    with open(path, encoding="utf-8") as f:
        model = json.load(f)["model"]
    end, table = model.get("end_of_word_suffix") or "", _byte_of()
    out = set()
    for token in model["vocab"]:
        if end and token.endswith(end):
            token = token[: -len(end)]
        if token and all(c in table for c in token):
            out.add(bytes(table[c] for c in token))
    return out


_LOADED: dict[str, LongestMatchAutomaton] = {}


def automaton(path: str | None = None) -> LongestMatchAutomaton:
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    if path not in _LOADED:
        _LOADED[path] = LongestMatchAutomaton(load_pieces(path))
    return _LOADED[path]


def _count(path: str | None):
    def run(batches):
        memo = _Memo(automaton(path))
        get = memo.__getitem__
        for whole in batches:
            for b in tk.sub_batches(whole, "text"):
                words, tokens, unknown = [], [], []
                for t in b.column("text").to_pylist():
                    w = (t or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
                    total = sum(map(get, w))
                    words.append(len(w))
                    tokens.append(total % _UNKNOWN)
                    unknown.append(total // _UNKNOWN)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(words, pa.int64()), pa.array(tokens, pa.int64()), pa.array(unknown, pa.int64())], names=["doc_id", "n_words", "n_tokens", "n_unknown"])

    return run


def token_counts(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """``(doc_id, n_words, n_tokens, n_unknown)``, a row per row of ``docs``."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_count(vocabulary), "doc_id long, n_words long, n_tokens long, n_unknown long")
