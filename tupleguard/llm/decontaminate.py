"""Benchmark decontamination by spaced-seed hashing.

Fixed masks choose some positions of a window of words and ignore the others, so windows that
differ only in ignored places hash alike. Seeds of the test items and of every training
document are joined on their hash (a fixed-size bit table turns most document windows away
first). Around each hit the item is laid over the document on that diagonal, and the best
segment under a substitution-tolerant score is taken. A document is contaminated by an item if
the item positions matched in such segments (on any diagonals, so insertions are bridged) are
at least ``WORDS`` words or half of the item, and eight at least.

Test sets are small beside the corpus, but their size is checked: they go out in slices of at
most ``SLICE`` bytes (or one longer item). A task holds one slice at a time and passes each
chunk of its documents by all of them, keeping the best item of every row by its place, so no
item is left out and a row's verdict depends on no other row, whatever their ids. The driver
holds one slice at a time.

Defined cases: null and wordless texts are clean; items shorter than a mask are one exact seed
of all their words; items of fewer than four words and null items match nothing; repeated
items and rows are allowed, rows that share an id are judged each by its own text; ties between
items go to the smaller item_id; empty tables give clean documents or no rows; null doc_ids are
allowed; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textkit as tk

#: The masks (1 is compared, 0 is ignored).
MASKS = ("11101011", "110110101", "1101000111", "10110011001")
#: Words of the shortest item that is searched, matched words that always suffice.
LEAST, WORDS = 4, 13
#: Share of an item's words, and the words at least, that make a match too.
SHARE, FEWEST = 0.5, 8
#: What a substituted word costs against a matching one (half identity, ``SHARE``, breaks even).
PENALTY = 1
#: Bytes of item text that are held by every task.
SLICE = 8 << 20
#: Bytes of documents that pass by several slices together.
CHUNK = 32 << 20
_BITS = 22

RESULT = "doc_id long, contaminated boolean, item_id long, matched int, item_words int"


def _seed_hashes(words: np.ndarray, mask: str, number: int) -> np.ndarray:
    """The seed at every start position (valid where the window fits)."""
    n = len(words) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    acc = np.full(n, number + 1, np.uint64)
    for j, bit in enumerate(mask):
        if bit == "1":
            acc += words[j : j + n] * (tk.mix(np.array([j + 100 * number + 7], np.uint64))[0] | np.uint64(1))
    return tk.mix(acc)


class Items:
    """Seeds of one slice of test items."""

    def __init__(self, rows: list[tuple[int, str]]):
        self.ids = [r[0] for r in rows]
        words, ptr = tk.hash_words(pa.array([r[1] for r in rows], pa.string()))
        self.words = [words[ptr[i] : ptr[i + 1]] for i in range(len(rows))]
        shapes = {m for m in MASKS}
        shapes |= {"1" * len(w) for w in self.words if LEAST <= len(w) < max(map(len, MASKS))}
        self.masks = sorted(shapes, key=lambda m: (len(m), m))
        seeds, where = [], []
        for number, mask in enumerate(self.masks):
            for i, w in enumerate(self.words):
                exact = mask == "1" * len(w)
                if mask not in MASKS and not exact:
                    continue
                h = _seed_hashes(w, mask, number)
                seeds.append(h)
                where += [(i, p) for p in range(len(h))]
        flat = np.concatenate(seeds) if seeds else np.zeros(0, np.uint64)
        order = np.argsort(flat, kind="stable")
        self.seeds = flat[order]
        self.where = np.array(where, np.int64).reshape(-1, 2)[order]
        self.bits = np.zeros(1 << _BITS, bool)
        self.bits[(self.seeds >> np.uint64(64 - _BITS)).astype(np.int64)] = True

    def hits(self, words: np.ndarray, ptr: np.ndarray):
        """(row, item, diagonal), distinct; the diagonal is document less item position."""
        found = []
        for number, mask in enumerate(self.masks):
            h = _seed_hashes(words, mask, number)
            pos = np.flatnonzero(self.bits[(h >> np.uint64(64 - _BITS)).astype(np.int64)])
            if not len(pos):
                continue
            lo, hi = np.searchsorted(self.seeds, h[pos], "left"), np.searchsorted(self.seeds, h[pos], "right")
            pos, lo, n = pos[hi > lo], lo[hi > lo], (hi - lo)[hi > lo]
            row = np.searchsorted(ptr, pos, "right") - 1
            fits = pos + len(mask) <= ptr[row + 1]
            pos, lo, n, row = pos[fits], lo[fits], n[fits], row[fits]
            if not len(pos):
                continue
            take = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            item = self.where[take]
            found.append(np.stack([np.repeat(row, n), item[:, 0], np.repeat(pos, n) - item[:, 1]], axis=1))
        return np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 3), np.int64)

    def verify(self, words: np.ndarray, ptr: np.ndarray, row: int, item: int, diagonals: np.ndarray) -> int:
        """Item positions that match around seeds of any diagonal, or half of the item and more on one."""
        own = self.words[item]
        covered = np.zeros(len(own), bool)
        most = 0
        for d in diagonals:
            a = max(0, int(ptr[row] - d))
            b = min(len(own), int(ptr[row + 1] - d))
            if b <= a:
                continue
            same = own[a:b] == words[d + a : d + b]
            covered[a:b] |= same & _around_seeds(same)
            most = max(most, int(same.sum()))
        matched = int(covered.sum())
        return max(matched, most) if most >= SHARE * len(own) else matched


def _around_seeds(same: np.ndarray) -> np.ndarray:
    """Positions in the best segments (matches less penalties) that hold a seed."""
    n = len(same)
    starts, ends = [], []
    for mask in MASKS if n >= len(MASKS[0]) else ("1" * n,):
        room = n - len(mask) + 1
        if room <= 0:
            continue
        hit = np.ones(room, bool)
        for j, bit in enumerate(mask):
            if bit == "1":
                hit &= same[j : j + room]
        at = np.flatnonzero(hit)
        starts.append(at)
        ends.append(at + len(mask))
    edge = np.zeros(n + 1, np.int64)
    if starts:
        s, e = np.concatenate(starts), np.concatenate(ends)
        total = np.concatenate(([0], np.cumsum(np.where(same, 1, -PENALTY))))
        at = np.arange(n + 1)
        lowest = np.maximum.accumulate(np.where(total == np.minimum.accumulate(total), at, 0))
        back = total[::-1]
        highest = n - np.maximum.accumulate(np.where(back == np.maximum.accumulate(back), at, 0))[::-1]
        np.add.at(edge, lowest[s], 1)
        np.add.at(edge, highest[e], -1)
    return np.cumsum(edge[:-1]) > 0


def enough(matched: int, item_words: int) -> bool:
    if item_words < LEAST:
        return False
    return matched >= min(WORDS, item_words) or (matched >= FEWEST and matched >= SHARE * item_words)


def _found(items: Items, b: pa.RecordBatch, best: list) -> None:
    """Betters ``best``, one entry a row, by the items: ``(-matched, item_id, item words)``."""
    words, ptr = tk.hash_words(b.column(b.schema.get_field_index("text")))
    hits = items.hits(words, ptr)
    if not len(hits):
        return
    cut = np.flatnonzero((np.diff(hits[:, 0]) != 0) | (np.diff(hits[:, 1]) != 0)) + 1
    for group in np.split(hits, cut):
        row, item = int(group[0, 0]), int(group[0, 1])
        m = items.verify(words, ptr, row, item, group[:, 2])
        if enough(m, len(items.words[item])):
            got = (-m, items.ids[item], len(items.words[item]))
            best[row] = got if best[row] is None else min(best[row], got)


def _judged(shared: list, batches):
    """Each sub-batch with the best item of each of its rows."""
    held: list[pa.RecordBatch] = []
    size = 0

    def judge():
        best = [[None] * b.num_rows for b in held]
        for part in shared:
            items = Items(part.value) if len(shared) > 1 else _single(part)
            for b, own in zip(held, best):
                _found(items, b, own)
        yield from zip(held, best)

    for whole in batches:
        for b in tk.sub_batches(whole, "text"):
            held.append(b)
            size += b.nbytes
            # one slice needs no larger chunk; several are read again for each
            if len(shared) == 1 or size >= CHUNK:
                yield from judge()
                held, size = [], 0
    if held:
        yield from judge()


_SINGLE: dict = {}


def _single(part) -> Items:
    """The seeds of an only slice, built once a worker."""
    rows = part.value
    if _SINGLE.get("rows") is not rows:
        _SINGLE.update(rows=rows, items=Items(rows))
    return _SINGLE["items"]


def _scan(shared: list):
    def run(batches):
        for b, best in _judged(shared, batches):
            yield pa.RecordBatch.from_arrays(
                [
                    b.column("doc_id"),
                    pa.array([x is not None for x in best]),
                    pa.array([x and x[1] for x in best], pa.int64()),
                    pa.array([0 if x is None else -x[0] for x in best], pa.int32()),
                    pa.array([x and x[2] for x in best], pa.int32()),
                ],
                names=["doc_id", "contaminated", "item_id", "matched", "item_words"],
            )

    return run


def slices(benchmark: DataFrame, most: int = SLICE):
    """The items in slices of bounded size, one after another."""
    rows = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long"), F.col("text").cast("string"))
    held, size = [], 0
    for r in rows.orderBy("item_id").toLocalIterator():
        n = len(r[1].encode("utf-8", "surrogatepass"))
        if held and size + n > most:
            yield held
            held, size = [], 0
        held.append((r[0], r[1]))
        size += n
    yield held


def _shared(benchmark: DataFrame, most: int) -> list:
    context = benchmark.sparkSession.sparkContext
    return [context.broadcast(part) for part in slices(benchmark, most)]


def scan(docs: DataFrame, benchmark: DataFrame, most: int = SLICE) -> DataFrame:
    """``(doc_id, contaminated, item_id, matched, item_words)``, a row per row of ``docs``;
    the item is the one with most matched words."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_scan(_shared(benchmark, most)), RESULT)


def clean(docs: DataFrame, benchmark: DataFrame, most: int = SLICE) -> DataFrame:
    """``docs`` without contaminated rows; all columns kept."""
    shared = _shared(benchmark, most)

    def run(batches):
        for b, best in _judged(shared, batches):
            yield b.filter(pa.array([x is None for x in best]))

    return docs.mapInArrow(run, docs.schema)
