"""Language identification by cross-parsing entropy.

For every language a suffix automaton of its labelled training text recognises exactly that
text's substrings. A document is parsed greedily into the longest phrases that occur in the
training text; few phrases mean that the language explains it well. Per language,
``phrases * log2(training length) / symbols`` estimates the cross entropy in bits per symbol;
the smallest wins (ties: the first in code order).

Texts are lower-cased, runs of non-letters become one space, every letter of any training text
is a symbol of its own, and letters that no training text holds are one more. The automaton is
completed to a dense transition table of its language's commonest letters (moves by its other
letters are found by binary search), so that tens of thousands of text segments of all documents
step through all languages' tables in lockstep (a few array operations a symbol position). Whole texts are read; a document is parsed in
segments of ``SEGMENT`` symbols, which costs at most one extra phrase a segment and bounds time
and memory for very long texts.

Training is on a bounded sample: per language ``TRAIN`` symbols, or all labelled text where there
is less, of ``DOCS`` labelled documents, the first by a hash of id and text, or of more where these are
too short. Documents share the length evenly as far as theirs allows; of a longer one, spans of at
most ``SPAN`` symbols are taken, one at a hashed place of every part of equal length.

Defined cases: null text and text without letters give ``und`` with score 0; null labels are
not learned from; without any labelled document every text is ``und``; repeated rows are
predicted alike; null ids are allowed; other columns are ignored.
"""

from __future__ import annotations

import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from . import textkit as tk
from .state import keep, release

#: Bounds of the training sample for each language, and of a span of a document.
DOCS, TRAIN = 96, 32_000
SPAN = 256
#: Symbols parsed in one go.
SEGMENT = 256
#: Columns of a dense table: 0 is the space, the last stands for letters outside of it.
SYMBOLS = 56
NONE = 65535


class SuffixAutomaton:
    """Online construction over a list of small integers."""

    def __init__(self, symbols):
        self.next: list[dict] = [{}]
        self.link, self.length = [-1], [0]
        last = 0
        for c in symbols:
            cur = len(self.next)
            self.next.append({})
            self.length.append(self.length[last] + 1)
            self.link.append(0)
            p = last
            while p >= 0 and c not in self.next[p]:
                self.next[p][c] = cur
                p = self.link[p]
            if p >= 0:
                q = self.next[p][c]
                if self.length[q] == self.length[p] + 1:
                    self.link[cur] = q
                else:
                    twin = len(self.next)
                    self.next.append(dict(self.next[q]))
                    self.length.append(self.length[p] + 1)
                    self.link.append(self.link[q])
                    while p >= 0 and self.next[p].get(c) == q:
                        self.next[p][c] = twin
                        p = self.link[p]
                    self.link[q] = self.link[cur] = twin
            last = cur

    def table(self, width: int) -> np.ndarray:
        out = np.full((len(self.next), width), NONE, np.uint16)
        for s, moves in enumerate(self.next):
            for c, t in moves.items():
                out[s, c] = t
        return out


class Transitions:
    """One language's completed automaton over the symbols of all languages.

    Its commonest symbols have dense columns; moves by its other ones are sorted keys, so no
    alphabet is too large; symbols that the language lacks lead nowhere."""

    def __init__(self, symbols: list[int], width: int):
        from collections import Counter

        made = SuffixAutomaton(symbols)
        seen = [c for c, _ in sorted(Counter(symbols).items(), key=lambda x: (x[0] != 0, -x[1], x[0]))]
        self.column = np.full(width, SYMBOLS - 1, np.uint8)
        self.column[seen[: SYMBOLS - 1]] = np.arange(len(seen[: SYMBOLS - 1]))
        dense = np.full((len(made.next), SYMBOLS), NONE, np.uint16)
        rest = []
        for s, moves in enumerate(made.next):
            for c, t in moves.items():
                if self.column[c] < SYMBOLS - 1:
                    dense[s, self.column[c]] = t
                else:
                    rest.append((s * width + c, t))
        self.flat, self.width = dense.ravel(), width
        self.rare = np.zeros(width, bool)
        self.rare[seen[SYMBOLS - 1 :]] = True
        pairs = np.array(sorted(rest), np.int64).reshape(-1, 2)
        self.keys, self.to = pairs[:, 0].copy(), pairs[:, 1].astype(np.uint16)

    def step(self, state: np.ndarray, c: np.ndarray) -> np.ndarray:
        out = self.flat[state * SYMBOLS + self.column[c]]
        if len(self.keys):
            at = np.flatnonzero(self.rare[c])
            if len(at):
                want = state[at] * self.width + c[at]
                pos = np.minimum(np.searchsorted(self.keys, want), len(self.keys) - 1)
                out[at] = np.where(self.keys[pos] == want, self.to[pos], NONE)
        return out

    def __getitem__(self, at: tuple[int, int]):
        return self.step(np.array([at[0]], np.int64), np.array([at[1]], np.int64))[0]


_ALPHA: np.ndarray | None = None


def _alpha() -> np.ndarray:
    global _ALPHA
    if _ALPHA is None:
        _ALPHA = np.array([chr(i).isalpha() for i in range(0x110000)])
    return _ALPHA


def code_points(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased code points of all texts, and each one's count."""
    low = [t.lower() for t in texts]
    data = np.frombuffer("".join(low).encode("utf-32-le", "surrogatepass"), np.uint32)
    return data, np.array([len(t) for t in low], np.int64)


def symbol_stream(texts: list[str], lut: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of each text with runs of non-letters collapsed, and where each begins."""
    cp, n = code_points(texts)
    ptr = np.zeros(len(n) + 1, np.int64)
    np.cumsum(n, out=ptr[1:])
    sym = lut[cp]
    space = sym == 0
    fresh = np.ones(len(sym), bool)
    fresh[1:] = ~(space[1:] & space[:-1])
    begin = ptr[:-1][n > 0]
    fresh[begin] = True
    kept = np.zeros(len(sym) + 1, np.int64)
    np.cumsum(fresh, out=kept[1:])
    return sym[fresh], kept[ptr]


class CrossParser:
    """The completed automata of all languages."""

    def __init__(self, samples: dict[str, list[str]]):
        self.langs = sorted(samples)
        letters = sorted({c for texts in samples.values() for t in texts for c in t.lower() if c.isalpha()})
        width = len(letters) + 2
        kind = np.min_scalar_type(width - 1)
        self.lut = np.where(_alpha(), width - 1, 0).astype(kind)
        self.lut[[ord(c) for c in letters]] = np.arange(1, width - 1)
        self.tables, self.bits = [], []
        for lang in self.langs:
            sym, _ = symbol_stream([" ".join(samples[lang])], self.lut)
            sym = sym[:TRAIN]
            self.tables.append(Transitions(sym.tolist(), width))
            self.bits.append(math.log2(max(2, len(sym))))

    def phrases(self, sym: np.ndarray, ptr: np.ndarray) -> np.ndarray:
        """Phrases of each row by each language (rows x languages)."""
        rows = len(ptr) - 1
        out = np.zeros((rows, len(self.langs)), np.int64)
        length = np.diff(ptr)
        segs = -(-length // SEGMENT)
        total = int(segs.sum())
        if not total:
            return out
        row = np.repeat(np.arange(rows), segs)
        k = np.arange(total) - np.repeat(np.cumsum(segs) - segs, segs)
        start = ptr[row] + k * SEGMENT
        size = np.minimum(SEGMENT, ptr[row + 1] - start)
        order = np.argsort(-size, kind="stable")
        row, start, size = row[order], start[order], size[order]
        longest = int(size[0])
        active = np.searchsorted(-size, -np.arange(longest), side="left")
        padded = np.concatenate((sym, np.zeros(SEGMENT, sym.dtype)))
        grid = np.ascontiguousarray(padded[start[:, None] + np.arange(longest)].T)
        for i, table in enumerate(self.tables):
            state = np.zeros(total, np.int64)
            count = np.zeros(total, np.int64)
            for t in range(longest):
                n = active[t]
                c = grid[t, :n]
                s = table.step(state[:n], c)
                failed = np.flatnonzero(s == NONE)
                if len(failed):
                    # the phrase ends before this symbol, which begins the next one
                    count[failed] += state[failed] != 0
                    again = table.step(np.zeros(len(failed), np.int64), c[failed])
                    unknown = again == NONE
                    count[failed] += unknown
                    again[unknown] = 0
                    s[failed] = again
                state[:n] = s
            count += state != 0
            np.add.at(out[:, i], row, count)
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        clean = [t or "" for t in texts]
        sym, ptr = symbol_stream(clean, self.lut)
        n = np.diff(ptr)
        letters = np.zeros(len(sym) + 1, np.int64)
        np.cumsum(sym != 0, out=letters[1:])
        known = np.diff(letters[ptr]) > 0
        if not self.langs:
            return ["und"] * len(clean), np.zeros(len(clean))
        bits = self.phrases(sym, ptr) * np.array(self.bits) / np.maximum(n, 1)[:, None]
        best = bits.argmin(axis=1)
        weight = np.exp2(-4 * (bits - bits.min(axis=1, keepdims=True)))
        score = weight.max(axis=1) / weight.sum(axis=1)
        return [self.langs[b] if k else "und" for b, k in zip(best, known)], np.where(known, score, 0.0)


def _letters(batches):
    """Texts as the parser sees them: lower case, runs of non-letters as one space."""
    for whole in batches:
        for b in tk.sub_batches(whole, "text"):
            texts = [" ".join("".join(c if c.isalpha() else " " for c in t.lower()).split()) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("lang"), b.column("doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array(texts, pa.string())], names=["lang", "doc_id", "n", "text"])


def _share(lengths: list[int]) -> int:
    """The most that a document may give so that all together give ``TRAIN``, or all they have."""
    left = TRAIN
    for i, n in enumerate(sorted(lengths)):
        share = -(-left // (len(lengths) - i))
        if n > share:
            return share
        left -= n
    return max(lengths, default=0)


def _spans(text: str, share: int) -> str:
    """``share`` symbols of the text, from all over it."""
    if len(text) <= share:
        return text
    k = -(-share // SPAN)
    size, seed, out = share // k, zlib.crc32(text.encode("utf-8", "surrogatepass")), []
    for j in range(k):
        low, high = len(text) * j // k, len(text) * (j + 1) // k
        at = low + zlib.crc32(f"{seed} {j}".encode()) % (high - low - size + 1)
        out.append(text[at : at + size])
    return " ".join(out)


def fit(docs: DataFrame, where=None) -> CrossParser:
    """Learns from the labelled rows of ``docs`` (those of ``where``)."""
    rows = docs.where("lang is not null and text is not null and length(text) > 0")
    if where is not None:
        rows = rows.where(where)
    # a document is known by its id and text: rows without an id count, repeated rows are one
    rows = rows.select(F.col("lang").cast("string").alias("lang"), F.xxhash64("doc_id", F.col("text").cast("string")).alias("doc_id"), F.col("text").cast("string").alias("text"))
    order = Window.partitionBy("lang").orderBy("doc_id")
    samples: dict[str, list[str]] = {}
    most, open_ = DOCS, None
    while open_ is None or open_:
        among = rows if open_ is None else rows.where(F.col("lang").isin(open_))
        chosen = keep(among.select("lang", "doc_id").distinct().withColumn("__n", F.row_number().over(order)).where(F.col("__n") <= most).select("lang", "doc_id"), "language-chosen")
        full = {r["lang"] for r in chosen.groupBy("lang").count().collect() if r["count"] >= most}
        texts = among.join(F.broadcast(chosen), ["lang", "doc_id"], "left_semi").distinct()
        read = keep(texts.select("lang", "doc_id", "text").mapInArrow(_letters, "lang string, doc_id long, n long, text string").where("n > 0"), "language-texts")
        lengths: dict[str, list[int]] = {}
        for r in read.select("lang", "n").collect():
            lengths.setdefault(r["lang"], []).append(r["n"])
        # of documents too short to fill the length, more are read
        open_ = [k for k in sorted(full) if sum(lengths.get(k, [])) < TRAIN and most < TRAIN]
        shares = {k: _share(n) for k, n in lengths.items() if k not in open_}

        def cut(batches, shares=shares):
            for b in batches:
                lang = b.column("lang").to_pylist()
                text = [_spans(t, shares[k]) if k in shares else "" for k, t in zip(lang, b.column("text").to_pylist())]
                yield pa.RecordBatch.from_arrays([b.column("lang"), b.column("doc_id"), pa.array(text, pa.string())], names=["lang", "doc_id", "text"])

        got = read.mapInArrow(cut, read.select("lang", "doc_id", "text").schema).where("text <> ''").collect()
        for r in sorted(got, key=lambda r: (r["lang"], r["doc_id"], r["text"])):
            samples.setdefault(r["lang"], []).append(r["text"])
        release(chosen, read)
        most *= 8
    return CrossParser(samples)


def identify(docs: DataFrame, model: CrossParser) -> DataFrame:
    """``docs`` with columns ``lang_pred`` and ``lang_score`` added (replaced where they exist)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = [c for c in docs.columns if c not in ("lang_pred", "lang_score")]
    base = docs.select(*names)
    schema = base.withColumn("lang_pred", F.lit("")).withColumn("lang_score", F.lit(0.0)).schema

    def run(batches):
        parser = shared.value
        for whole in batches:
            for b in tk.sub_batches(whole, "text", 1 << 20):
                lang, score = parser.predict(b.column(b.schema.get_field_index("text")).to_pylist())
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*b.schema.names, "lang_pred", "lang_score"])

    return base.mapInArrow(run, schema)
