"""Language-model scoring with an interpolated modified Kneser-Ney n-gram model of any order.

Counting runs in Spark: tasks count words, and then n-grams of the order, of their own texts
with array sorts and ship one packed block per bucket (distinct n-grams as word numbers, small for
frequent words, in compressed byte planes). Buckets are merged by array sorts again. N-grams are dealt
by the last word of their context, so the counts of all lower orders (distinct left extensions)
and all contexts' statistics arise in the same bucket without another shuffle. The few words
that occur more often than a bucket holds tokens are dealt by the word before and the word
after instead; what then arises in parts (their word pairs and contexts) is summed in the one
further shuffle that gathers the words' own continuation counts.

Every bucket is stored as one file of sorted hash arrays and counts in the shared folder, named
by its number; scoring tasks memory-map the files that their batch needs, at most ``OPEN`` at a
time, in order, and look up whole batches by binary search. Nothing that grows with the corpus
passes through the driver but the list of those frequent words: it sees sums. N-grams and
contexts are known by 32 bits of hash within their bucket of about a million, so about one in
four thousand unseen n-grams is taken for another; words are known by 64 bits.

Tokens are words (A-Z lowered) and one end per text. An n-gram's probability is its count less a
discount of its class (1, 2, 3 and more) over its context's count, plus the discounts' mass
times the probability at the next lower order. Lower orders count distinct left extensions;
n-grams at a text's beginning have none and keep their number of occurrences. The lowest order
is interpolated with the uniform distribution over the known words and one unknown.

Defined cases: null and blank texts are the end token alone; with no training text the base
probability is that of the formula with zero counts and the model is uniform; texts shorter than
the order use the orders that they reach; repeated rows are counted and scored as often as they
occur; null ids are allowed; other columns are ignored.
"""

from __future__ import annotations

import json
import os
import uuid
from collections import OrderedDict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textkit as tk
from .state import shared_path
from .warc import _open_fs

U = np.uint64
END = U(0x1111111111111111)
#: Text bytes of a bucket, about; tokens that a task counts before it ships them; mapped files.
BUCKET, FLUSH, OPEN = 8 << 20, 2_000_000, 32
ORDER = 3
_MUL = U(0x9E3779B97F4A7C15)
#: Word numbers in n-grams: nothing (beyond the beginning), the beginning, a word that the
#: training text lacks; known words follow from 2.
NONE, BEGUN, UNKNOWN = U(0), U(1), U((1 << 64) - 1)


def _short(h: np.ndarray) -> np.ndarray:
    return h >> U(24)


def _bucket_of(short: np.ndarray, buckets: int) -> np.ndarray:
    return (short % U(buckets)).astype(np.int64)


def _dealt(number: np.ndarray, buckets: int) -> np.ndarray:
    """The bucket of a word number (or of any other)."""
    return ((number - U(2)) % U(buckets)).astype(np.int64)


def _small(counts: np.ndarray) -> bytes:
    """Counts as bytes, 255 for those listed after them."""
    big = counts[counts >= 255]
    return np.uint64(len(big)).tobytes() + np.minimum(counts, 255).astype(np.uint8).tobytes() + big.astype("<u8").tobytes()


def _unsmall(b: bytes, n: int) -> np.ndarray:
    k = int(np.frombuffer(b[:8], "<u8")[0])
    out = np.frombuffer(b[8 : 8 + n], np.uint8).astype(np.int64)
    if k:
        out[out == 255] = np.frombuffer(b[8 + n : 8 + n + 8 * k], "<u8").astype(np.int64)
    return out


def _sum_by(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and the sums of their counts."""
    if not len(keys):
        return keys, np.zeros(0, np.int64)
    if counts is None:
        return np.unique(keys, return_counts=True)
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    first = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
    return k[first], np.add.reduceat(counts[order], first)


def _tokens(column) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes with an end after each text."""
    words, ptr = tk.hash_words(column)
    n = np.diff(ptr)
    out_ptr = np.concatenate(([0], np.cumsum(n + 1)))
    out = np.empty(int(out_ptr[-1]), U)
    out[out_ptr[1:] - 1] = END
    mask = np.ones(len(out), bool)
    mask[out_ptr[1:] - 1] = False
    out[mask] = words
    return out, out_ptr


def _contexts(word: np.ndarray, ptr: np.ndarray, n: int, nothing, begun) -> list[np.ndarray]:
    """The ``n`` words before each token, nearest first."""
    place = np.arange(len(word)) - np.repeat(ptr[:-1], np.diff(ptr))
    out = []
    for j in range(1, n + 1):
        before = np.full(len(word), nothing, word.dtype)
        before[j:] = word[:-j] if j < len(word) else word[:0]
        before[place < j] = nothing
        before[place == j - 1] = begun
        out.append(before)
    return out


def _context_key(cols: list[np.ndarray]) -> np.ndarray:
    key = tk.mix(cols[0])
    for c in cols[1:]:
        key = tk.mix(key * _MUL + c)
    return key


def _gram_key(context: np.ndarray, w: np.ndarray) -> np.ndarray:
    return tk.mix(context * _MUL + tk.mix(w))


def _low(key: np.ndarray) -> np.ndarray:
    """What identifies a key within its bucket."""
    return (key >> U(32)).astype(np.uint32)


def _in(values: np.ndarray, sorted_: np.ndarray) -> np.ndarray:
    if not len(sorted_):
        return np.zeros(len(values), bool)
    at = np.searchsorted(sorted_, values)
    at[at == len(sorted_)] = 0
    return sorted_[at] == values


def _spread(cols: list[np.ndarray], w: np.ndarray) -> np.ndarray:
    """What n-grams with a frequent last context word are dealt by."""
    if len(cols) < 2:
        return w
    return np.where(cols[1] == NONE, w, tk.mix(cols[1] + tk.mix(w) * _MUL))


_FIELDS = pa.schema([("kind", pa.string()), ("bucket", pa.int32()), ("block", pa.binary()), ("key", pa.int64()), ("facts", pa.list_(pa.int64()))])
SHAPE = "kind string, bucket int, block binary, key long, facts array<long>"


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    """Rows ``(kind, bucket, block, key, facts)``."""
    cols = list(zip(*rows)) if rows else [[]] * 5
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, _FIELDS)], schema=_FIELDS)


def _fact(kind: str, bucket: int, key: int, values) -> tuple:
    return kind, bucket, None, key, [int(v) for v in values]


def _planes(x: np.ndarray) -> bytes:
    """Numbers as byte planes, as many as the largest needs."""
    width = max(1, -(-int(x.max()).bit_length() // 8)) if len(x) else 1
    return bytes([width]) + np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def _unplanes(b: bytes, at: int, n: int) -> tuple[np.ndarray, int]:
    width = b[at]
    out = np.zeros((n, 8), np.uint8)
    out[:, :width] = np.frombuffer(b, np.uint8, width * n, at + 1).reshape(width, n).T
    return out.view("<u8").ravel().astype(U), at + 1 + width * n


def _pack(cols: list[np.ndarray], counts: list[np.ndarray]) -> bytes:
    """Sorted rows of word numbers and counts. Of each column only what differs from the row
    before is stored, with the lengths of the runs."""
    n = len(cols[0])
    new, parts, sizes = np.zeros(n, bool), [], [n, len(cols), len(counts)]
    new[:1] = True
    for i, c in enumerate(cols):
        if i < len(cols) - 1:
            new[1:] |= c[1:] != c[:-1]
            at = np.flatnonzero(new)
            sizes.append(len(at))
            parts += [_planes(c[at]), _small(np.diff(np.append(at, n)))]
        else:
            parts.append(_planes(c))
    body = b"".join(parts + [_small(c) for c in counts])
    head = np.array([*sizes, len(body)], "<u8").tobytes()
    return np.uint64(len(head)).tobytes() + head + pa.compress(body, codec="zstd", asbytes=True)


def _unpack(block: bytes) -> tuple[list[np.ndarray], list[np.ndarray]]:
    size = int(np.frombuffer(block[:8], "<u8")[0])
    n, k, many, *runs, length = (int(x) for x in np.frombuffer(block[8 : 8 + size], "<u8"))
    body = pa.decompress(block[8 + size :], decompressed_size=length, codec="zstd", asbytes=True)
    at = 0

    def small(m):
        nonlocal at
        big = int(np.frombuffer(body[at : at + 8], "<u8")[0])
        out = _unsmall(body[at : at + 8 + m + 8 * big], m)
        at += 8 + m + 8 * big
        return out

    cols = []
    for i in range(k):
        c, at = _unplanes(body, at, runs[i] if i < k - 1 else n)
        cols.append(np.repeat(c, small(runs[i])) if i < k - 1 else c)
    return cols, [small(n) for _ in range(many)]


def _together(blocks: list[bytes]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    parts = [_unpack(b) for b in blocks]
    return [np.concatenate(x) for x in zip(*(p[0] for p in parts))], [np.concatenate(x) for x in zip(*(p[1] for p in parts))]


def _code(cols: list[np.ndarray]) -> np.ndarray:
    """One number a row that orders rows as their columns do."""
    code, size = cols[0], int(cols[0].max(initial=0)) + 1
    for c in cols[1:]:
        m = int(c.max(initial=0)) + 1
        if size * m >= 1 << 63:
            found, code = np.unique(code, return_inverse=True)
            code, size = code.astype(U), len(found)
            if size * m >= 1 << 63:
                found, c = np.unique(c, return_inverse=True)
                c, m = c.astype(U), len(found)
        code, size = code * U(m) + c, size * m
    return code


def _distinct(cols: list[np.ndarray], counts: list[np.ndarray]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Sorted distinct rows and the sums of their counts."""
    code = _code(cols)
    order = np.argsort(code)
    code = code[order]
    first = np.flatnonzero(np.concatenate(([True], code[1:] != code[:-1]))) if len(code) else order
    return [c[order[first]] for c in cols], [np.add.reduceat(c[order], first) if len(first) else c for c in counts]


def _blocks(kind: str, bucket: np.ndarray, cols: list[np.ndarray], counts: list[np.ndarray], key: int = 0):
    """One packed row for each bucket; the rows are sorted."""
    order = np.argsort(bucket, kind="stable")
    own, first = np.unique(bucket[order], return_index=True)
    for b, at in zip(own.tolist(), np.split(order, first[1:])):
        yield kind, b, _pack([c[at] for c in cols], [c[at] for c in counts]), key, None


def _count_words(buckets: int):
    def flush(held):
        keys, counts = _sum_by(np.concatenate(held))
        b = _bucket_of(_short(keys), buckets)
        order = np.argsort(b, kind="stable")
        cut = np.searchsorted(b[order], np.arange(buckets + 1))
        for i in range(buckets):
            at = order[cut[i] : cut[i + 1]]
            if len(at):
                yield _rows([("w", i, np.uint64(len(at)).tobytes() + keys[at].astype("<u8").tobytes() + _small(counts[at]), 0, None)])

    def run(batches):
        held, n = [], 0
        for whole in batches:
            for b in tk.sub_batches(whole, "text"):
                tokens, _ = _tokens(b.column("text"))
                held.append(tokens)
                n += len(tokens)
                if n >= FLUSH:
                    yield from flush(held)
                    held, n = [], 0
        if held:
            yield from flush(held)

    return run


def _write(folder: str, name: str, arrays: dict[str, np.ndarray]) -> None:
    """One file: what it holds, then the arrays. It appears under its name when it is whole; an
    attempt that runs again writes the same."""
    filesystem, root = _open_fs(folder)
    about, at = {}, 0
    for key, a in arrays.items():
        about[key] = (a.dtype.str, len(a), at)
        at += a.nbytes + -a.nbytes % 8
    head = json.dumps(about).encode()
    head += b" " * (-len(head) % 8)
    mine = f"{root}/{name}.{uuid.uuid4().hex}"
    with filesystem.open_output_stream(mine, compression=None) as out:
        out.write(np.uint64(len(head)).tobytes() + head)
        for a in arrays.values():
            out.write(np.ascontiguousarray(a).tobytes() + b"\0" * (-a.nbytes % 8))
    try:
        filesystem.move(mine, f"{root}/{name}")
    except OSError:
        if filesystem.get_file_info(f"{root}/{name}").size < 0:
            raise
        filesystem.delete_file(mine)


def _counted(name: str, key: np.ndarray, counts: np.ndarray) -> dict[str, np.ndarray]:
    """Arrays of a table of counts: bytes, 255 for those listed apart."""
    order = np.argsort(key, kind="stable")
    key, counts = key[order], counts[order]
    big = np.flatnonzero(counts >= 255)
    return {name: key, f"{name}.n": np.minimum(counts, 255).astype(np.uint8), f"{name}.at": big.astype(np.uint32), f"{name}.big": counts[big].astype(U)}


def _classed(name: str, key: np.ndarray, stats: np.ndarray) -> dict[str, np.ndarray]:
    """Arrays of a table of contexts ``(total, n1, n2, n3+)``: one byte where all counts are 1 and
    2 and few, 255 for those listed apart."""
    order = np.argsort(key, kind="stable")
    key, stats = key[order], stats[order]
    plain = (stats[:, 3] == 0) & (stats[:, 1] < 16) & (stats[:, 2] < 15)
    big = np.flatnonzero(~plain)
    code = np.where(plain, stats[:, 2] * 16 + stats[:, 1], 255).astype(np.uint8)
    code[big] = 255
    kind = np.uint32 if not len(big) or stats[big].max() < 2**32 else U
    return {name: key, f"{name}.n": code, f"{name}.at": big.astype(np.uint32), f"{name}.big": stats[big].astype(kind).ravel()}


def _read_counts(a: dict, name: str, pos: np.ndarray) -> np.ndarray:
    n = a[f"{name}.n"][pos].astype(np.int64)
    full = np.flatnonzero(n == 255)
    if len(full):
        n[full] = a[f"{name}.big"][np.searchsorted(a[f"{name}.at"], pos[full].astype(np.uint32))]
    return n


def _read_classes(a: dict, name: str, pos: np.ndarray) -> np.ndarray:
    code = a[f"{name}.n"][pos].astype(np.int64)
    n1, n2 = code & 15, code >> 4
    out = np.stack([n1 + 2 * n2, n1, n2, np.zeros_like(n1)], axis=1)
    full = np.flatnonzero(code == 255)
    if len(full):
        out[full] = np.asarray(a[f"{name}.big"]).reshape(-1, 4)[np.searchsorted(a[f"{name}.at"], pos[full].astype(np.uint32))]
    return out


def _number(rank, bucket, buckets: int):
    """A word's number in n-grams; its bucket is the number's remainder, less 2."""
    return rank * buckets + bucket + 2


def _merge_words(folder: str, frequent: int, buckets: int):
    def run(key, table):
        bucket = key[0].as_py()
        keys, counts = [], []
        for block in table.column("block").to_pylist():
            n = int(np.frombuffer(block[:8], "<u8")[0])
            keys.append(np.frombuffer(block[8 : 8 + 8 * n], "<u8").astype(U))
            counts.append(_unsmall(block[8 + 8 * n :], n))
        k, c = _sum_by(np.concatenate(keys), np.concatenate(counts))
        # frequent words have small numbers
        rank = np.empty(len(k), np.uint32)
        rank[np.argsort(-c, kind="stable")] = np.arange(len(k))
        _write(folder, f"words-{bucket}", {"hash": k, "count": c.astype(np.uint32 if c.max() < 2**32 else U), "rank": rank})
        rows = [_fact("words", bucket, 0, [len(k), c.sum()])]
        rows += [_fact("hot", bucket, _number(int(rank[i]), bucket, buckets), [1]) for i in np.flatnonzero(c > frequent) if k[i] != END]
        return pa.Table.from_batches([_rows(rows)])

    return run


def _count_grams(model: KneserNey):
    order, buckets, hot = model.order, model.buckets, model.hot

    def flush(held):
        words, rank = np.unique(np.concatenate([h[0] for h in held]), return_inverse=True)
        # n-grams of places in the order of word numbers pack into one number where they fit
        number = np.concatenate((np.array([NONE, BEGUN], U), model.numbers(words)[1]))
        sort = np.argsort(number)
        place = np.empty(len(sort), U)
        place[sort] = np.arange(len(sort), dtype=U)
        number, rank = number[sort], place[2:][rank]
        fits, at, parts = len(number).bit_length() * order <= 63, 0, []
        for tokens, ptr in held:
            own = rank[at : at + len(tokens)]
            at += len(tokens)
            cols = [*_contexts(own, ptr, order - 1, U(0), U(1)), own]
            if fits:
                code = cols[0]
                for c in cols[1:]:
                    code = code * U(len(number)) + c
                parts.append(code)
            else:
                parts.append(cols)
        held.clear()
        del rank, place, sort, words, own, cols
        if fits:
            code = np.concatenate(parts)
            parts.clear()
            code.sort()
            first = np.flatnonzero(np.concatenate(([True], code[1:] != code[:-1])))
            counts, code, cols = np.diff(np.append(first, len(code))), code[first], []
            for _ in range(order):
                cols.insert(0, number[(code % U(len(number))).astype(np.int64)])
                code //= U(len(number))
        else:
            cols = [np.concatenate(x) for x in zip(*parts)]
            cols, (counts,) = _distinct(cols, [np.ones(len(cols[0]), np.int64)])
            cols = [number[c.astype(np.int64)] for c in cols]
        *ctx, w = cols
        b = np.where(_in(ctx[0], hot), _dealt(_spread(ctx, w), buckets), _dealt(ctx[0], buckets))
        for row in _blocks("g", b, cols, [counts]):
            yield _rows([row])

    def run(batches):
        held, n = [], 0
        for whole in batches:
            for b in tk.sub_batches(whole, "text"):
                held.append(_tokens(b.column("text")))
                n += len(held[-1][0])
                if n >= FLUSH:
                    yield from flush(held)
                    held, n = [], 0
        if held:
            yield from flush(held)

    return run


def _of_counts(c: np.ndarray) -> list[int]:
    return [int((c == i).sum()) for i in (1, 2, 3, 4)]


def _context_stats(cols: list[np.ndarray], counts: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Distinct contexts and ``(total, n1, n2, n3+)`` of each."""
    found, stats = _distinct(cols, [counts, *((counts == i).astype(np.int64) for i in (1, 2)), (counts >= 3).astype(np.int64)])
    return found, np.stack(stats, axis=1)


def _merge_grams(folder: str, order: int, buckets: int, hot: np.ndarray):
    def run(key, table):
        bucket = key[0].as_py()
        cols, (counts,) = _together(table.column("block").to_pylist())
        cols, (counts,) = _distinct(cols, [counts])
        *ctx, w = cols
        # the order that each row reaches: texts' beginnings have shorter contexts
        reach = 1 + sum((c != NONE).astype(np.int64) for c in ctx)
        rows, arrays, above = [], {}, None
        for k in range(order, 1, -1):
            own = np.flatnonzero(reach == k)
            grams, n = [*(c[own] for c in ctx[: k - 1]), w[own]], counts[own]
            if above is not None:
                # distinct left extensions of the n-grams of the order above
                grams = [np.concatenate(x) for x in zip([*above[: k - 1], above[-1]], grams)]
                n = np.concatenate((np.ones(len(above[-1]), np.int64), n))
                grams, (n,) = _distinct(grams, [n])
            above = grams
            known = _in(grams[0], hot)
            if k == 2:
                break
            rows.append(_fact("f", bucket, k, _of_counts(n)))
            arrays |= _counted(f"g{k}", _low(_gram_key(_context_key(grams[:-1]), grams[-1])), n)
            for which, parts in ((~known, False), (known, True)):
                if not which.any():
                    continue
                found, stats = _context_stats([g[which] for g in grams[:-1]], n[which])
                if parts:
                    rows += _blocks("x", _dealt(_context_key(found), buckets), found, list(stats.T), k)
                else:
                    arrays |= _classed(f"x{k}", _low(_context_key(found)), stats)
        (v, u), cold = grams, ~known
        if known.any():
            rows += _blocks("h", _dealt(u[known], buckets), [v[known], u[known]], [n[known]])
        if cold.any():
            rows.append(_fact("f", bucket, 2, _of_counts(n[cold])))
            arrays |= _counted("g2", _low(_gram_key(_context_key([v[cold]]), u[cold])), n[cold])
            found, stats = _context_stats([v[cold]], n[cold])
            arrays |= _classed("x2", _low(_context_key(found)), stats)
            uw, un = _sum_by(u[cold])
            rows += _blocks("c", _dealt(uw, buckets), [uw], [un])
        _write(folder, f"grams-{bucket}", arrays)
        return pa.Table.from_batches([_rows(rows)])

    return run


def _merge_parts(folder: str):
    def run(key, table):
        bucket = key[0].as_py()
        by: dict = {}
        rows = []
        for kind, block, number, facts in zip(*(table.column(c).to_pylist() for c in ("kind", "block", "key", "facts"))):
            if kind == "f":
                rows.append((kind, bucket, None, number, facts))
            else:
                by.setdefault((kind, number), []).append(block)
        arrays = {}
        words, conts = [], []
        if ("c", 0) in by:
            (w,), (n,) = _together(by.pop(("c", 0)))
            words.append(w)
            conts.append(n)
        if ("h", 0) in by:
            cols, counts = _together(by.pop(("h", 0)))
            (v, w), (n,) = _distinct(cols, counts)
            arrays |= _counted("h2", _low(_gram_key(_context_key([v]), w)), n)
            rows.append(_fact("f", bucket, 2, _of_counts(n)))
            (found,), stats = _context_stats([v], n)
            rows += [_fact("hot", bucket, int(x), s) for x, s in zip(found, stats)]
            words.append(w)
            conts.append(np.ones(len(w), np.int64))
        for (_, k), blocks in by.items():
            found, stats = _distinct(*_together(blocks))
            arrays |= _classed(f"x{k}", _low(_context_key(found)), np.stack(stats, axis=1))
        if words:
            w, n = _sum_by(np.concatenate(words), np.concatenate(conts))
            arrays |= _counted("cont", _low(tk.mix(w)), n)
            rows.append(_fact("f", bucket, 1, [*_of_counts(n), (n >= 3).sum(), n.sum()]))
        if arrays:
            _write(folder, f"parts-{bucket}", arrays)
        return pa.Table.from_batches([_rows(rows)])

    return run


def discounts(n: list[int]) -> np.ndarray:
    """Discounts by count class 0, 1, 2, 3+ from the counts of counts 1 to 4."""
    n1, n2, n3, n4 = n[:4]
    y = n1 / (n1 + 2 * n2) if n1 + 2 * n2 else 0.5
    d = [0.0, 1 - 2 * y * n2 / n1 if n1 else 0.5, 2 - 3 * y * n3 / n2 if n2 else 1.0, 3 - 4 * y * n4 / n3 if n3 else 1.5]
    return np.array([0.0, *(min(max(x, 0.05), i - 0.05) for i, x in enumerate(d[1:], 1))])


class KneserNey:
    """Where the stored arrays are, and the model's global figures; files are memory-mapped."""

    def __init__(self, folder: str, buckets: int, order: int):
        self.folder, self.buckets, self.order = folder, buckets, order
        self.tokens = self.distinct = 0
        #: Frequent words, sorted, and ``(total, n1, n2, n3+)`` of each as a context.
        self.hot = np.zeros(0, U)
        self.hot_stats = np.zeros((0, 4), np.int64)
        self.d = {k: discounts([0, 0, 0, 0]) for k in range(1, order + 1)}
        self.uni_total, self.uni_mass = 0, 0.0
        self._open: OrderedDict = OrderedDict()

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_open"}

    def __setstate__(self, state):
        self.__dict__ = state | {"_open": OrderedDict()}

    def _arrays(self, name: str) -> dict:
        if name in self._open:
            self._open.move_to_end(name)
            return self._open[name]
        local = _local_file(self.folder, name)
        got = {}
        if local is not None:
            with open(local, "rb") as f:
                size = int(np.frombuffer(f.read(8), "<u8")[0])
                about = json.loads(f.read(size))
            whole = np.memmap(local, np.uint8, "r")
            for key, (kind, n, at) in about.items():
                got[key] = whole[8 + size + at : 8 + size + at + n * np.dtype(kind).itemsize].view(kind)
        self._open[name] = got
        while len(self._open) > OPEN:
            self._open.popitem(last=False)
        return got

    def _lookup(self, tables: tuple, which, bucket: np.ndarray, keys: np.ndarray, read, width: int = 0) -> np.ndarray:
        """``read(arrays, table, positions)`` for the keys that their bucket holds, 0 for others;
        ``which`` of the tables ``(file stem, table)`` each key is sought in."""
        out = np.zeros((len(keys), width) if width else len(keys), np.int64)
        # keys of 32 bits sort together with their bucket in one go
        file = bucket + self.buckets * np.asarray(which, np.int64)
        if keys.dtype == np.uint32 and 2 * self.buckets < 1 << 31:
            order = np.argsort((file << 32) | keys)
        else:
            order = np.lexsort((keys, file))
        file = file[order]
        first = np.flatnonzero(np.concatenate(([True], file[1:] != file[:-1]))) if len(file) else file
        for f, at in zip(file[first].tolist(), np.split(order, first[1:])):
            stem, table = tables[f // self.buckets]
            arrays = self._arrays(f"{stem}-{f % self.buckets}")
            if not len(arrays.get(table, ())):
                continue
            q, have = keys[at], arrays[table]
            pos = np.searchsorted(have, q)
            pos[pos == len(have)] = 0
            hit = have[pos] == q
            out[at[hit]] = read(arrays, table, pos[hit])
        return out

    def numbers(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Counts and numbers of words by their hashes."""
        bucket = _bucket_of(_short(words), self.buckets)
        got = self._lookup((("words", "hash"),), 0, bucket, words, lambda a, _, p: np.stack([a["count"][p].astype(np.int64), a["rank"][p].astype(np.int64)], axis=1), 2)
        return got[:, 0], np.where(got[:, 0] > 0, _number(got[:, 1], bucket, self.buckets).astype(U), UNKNOWN)

    def _grams(self, k: int, cols: list[np.ndarray], w: np.ndarray, key: np.ndarray, hot: np.ndarray) -> np.ndarray:
        """Counts of n-grams of order ``k``."""
        often = w if k == 2 else _spread(cols, w)
        place = _dealt(np.where(hot, often, cols[0]), self.buckets)
        return self._lookup((("grams", f"g{k}"), ("parts", "h2")), hot if k == 2 else 0, place, _low(key), _read_counts)

    def _stats(self, k: int, cols: list[np.ndarray], key: np.ndarray, hot: np.ndarray) -> np.ndarray:
        """``(total, n1, n2, n3+)`` of contexts of ``k - 1`` words."""
        if k > 2:
            place = _dealt(np.where(hot, key, cols[0]), self.buckets)
            return self._lookup((("grams", f"x{k}"), ("parts", f"x{k}")), hot, place, _low(key), _read_classes, 4)
        out = np.zeros((len(key), 4), np.int64)
        cold, often = np.flatnonzero(~hot), np.flatnonzero(hot)
        # words repeat: each is sought once
        found, of = np.unique(cols[0][cold], return_inverse=True)
        out[cold] = self._lookup((("grams", "x2"),), 0, _dealt(found, self.buckets), _low(_context_key([found])), _read_classes, 4)[of]
        out[often] = self.hot_stats[np.searchsorted(self.hot, cols[0][often])]
        return out

    def score(self, tokens: np.ndarray, ptr: np.ndarray):
        """Of each row: known tokens, base and model log10 probability."""
        uniq, inv = np.unique(tokens, return_inverse=True)
        c, number = self.numbers(uniq)
        base = np.log10((c + 1) / (self.tokens + 1.0 * (self.distinct + 1)))
        starts = ptr[:-1]
        known = np.add.reduceat((c > 0)[inv].astype(np.int64), starts)
        total = np.add.reduceat(base[inv], starts)
        uni = np.full(len(uniq), 1.0 / (self.distinct + 1))
        if self.uni_total:
            cont = self._lookup((("parts", "cont"),), 0, _dealt(number, self.buckets), _low(tk.mix(number)), _read_counts)
            cont[c == 0] = 0
            uni = np.maximum(cont - self.d[1][np.minimum(cont, 3)], 0) / self.uni_total + self.uni_mass / self.uni_total * uni
        p, word = uni[inv], number[inv]
        before = _contexts(word, ptr, self.order - 1, NONE, BEGUN)
        # rows whose context reaches so far and is of known words
        at, context = np.arange(len(word)), None
        for k in range(2, self.order + 1):
            far = before[k - 2][at]
            here = (far != NONE) & (far != UNKNOWN)
            at, far = at[here], far[here]
            if not len(at):
                break
            context = tk.mix(far) if context is None else tk.mix(context[here] * _MUL + far)
            cols = [b[at] for b in before[: k - 1]]
            hot = _in(cols[0], self.hot)
            stats = self._stats(k, cols, context, hot)
            n = np.zeros(len(at), np.int64)
            # an n-gram of an unseen context is unseen
            own = np.flatnonzero((word[at] != UNKNOWN) & (stats[:, 0] > 0))
            n[own] = self._grams(k, [b[own] for b in cols], word[at[own]], _gram_key(context[own], word[at[own]]), hot[own])
            high, denom, mass = np.maximum(n - self.d[k][np.minimum(n, 3)], 0), stats[:, 0], stats[:, 1:] @ self.d[k][1:]
            p[at] = np.where(denom > 0, (high + mass * p[at]) / np.maximum(denom, 1), p[at])
            # contexts beyond an unseen one are unseen too
            seen = denom > 0
            at, context = at[seen], context[seen]
        return known, total, np.add.reduceat(np.log10(p), starts)


def _local_file(folder: str, name: str) -> str | None:
    """A path that can be mapped: the shared file itself, or a copy where the shared folder is
    no file system of this machine; None where there is no such file."""
    import tempfile

    filesystem, root = _open_fs(folder)
    if filesystem.type_name == "local":
        return f"{root}/{name}" if os.path.exists(f"{root}/{name}") else None
    copy = os.path.join(tempfile.gettempdir(), f"{folder.rstrip('/').rsplit('/', 1)[-1]}-{name}")
    if not os.path.exists(copy):
        if filesystem.get_file_info(f"{root}/{name}").size is None:
            return None
        part = f"{copy}.{uuid.uuid4().hex}"
        with filesystem.open_input_stream(f"{root}/{name}") as src, open(part, "wb") as out:
            while chunk := src.read(8 << 20):
                out.write(chunk)
        os.replace(part, copy)
    return copy


def _sums(df: DataFrame) -> list:
    """Facts summed by kind and key, ``(kind, key, list)``: rows for sums and frequent words."""
    wide = df.groupBy("kind", "key").agg(*[F.sum(F.expr(f"coalesce(get(facts, {i}), 0L)")).alias(f"f{i}") for i in range(6)])
    return [(r["kind"], r["key"], [r[f"f{i}"] for i in range(6)]) for r in wide.collect()]


def fit(docs: DataFrame, where=None, bucket_bytes: int = BUCKET, order: int = ORDER) -> KneserNey:
    """Counts the texts of ``docs`` (those of ``where``) and stores the model of the given order
    (2 at least)."""
    spark = docs.sparkSession
    rows = docs if where is None else docs.where(where)
    rows = rows.select(F.col("text").cast("string").alias("text"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0]
    buckets = max(8, -(-int(size or 0) // bucket_bytes))
    folder = shared_path(spark, "ngrams")
    filesystem, root = _open_fs(folder)
    filesystem.create_dir(root, recursive=True)
    model = KneserNey(folder, buckets, order)
    # a word is frequent if its occurrences would fill a good third of a bucket (words of six bytes)
    words = rows.mapInArrow(_count_words(buckets), SHAPE).repartition(buckets, "bucket")
    hot = [int(BEGUN)]
    for kind, key, f in _sums(words.groupBy("bucket").applyInArrow(_merge_words(folder, bucket_bytes // 16, buckets), SHAPE)):
        if kind == "words":
            model.distinct, model.tokens = f[:2]
        else:
            hot.append(key)
    model.hot = np.unique(np.array(hot, U))
    model.hot_stats = np.zeros((len(model.hot), 4), np.int64)
    counted = rows.mapInArrow(_count_grams(model), SHAPE).repartition(buckets, "bucket")
    merged = counted.groupBy("bucket").applyInArrow(_merge_grams(folder, order, buckets, model.hot), SHAPE).repartition(buckets, "bucket")
    for kind, key, f in _sums(merged.groupBy("bucket").applyInArrow(_merge_parts(folder), SHAPE)):
        if kind == "hot":
            model.hot_stats[np.searchsorted(model.hot, U(key))] = f[:4]
        else:
            model.d[key] = discounts(f)
            if key == 1:
                model.uni_total = f[5]
                model.uni_mass = float(model.d[1][1] * f[0] + model.d[1][2] * f[1] + model.d[1][3] * f[4])
    return model


def score(docs: DataFrame, model: KneserNey) -> DataFrame:
    """``(doc_id, n_tokens, n_known, train_tokens, base_score, score)``, a row per row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for whole in batches:
            for b in tk.sub_batches(whole, "text"):
                tokens, ptr = _tokens(b.column("text"))
                if not b.num_rows:
                    continue
                known, base, got = m.score(tokens, ptr)
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id"), pa.array(np.diff(ptr)), pa.array(known), pa.array(np.full(b.num_rows, m.tokens, np.int64)), pa.array(base), pa.array(got)],
                    names=["doc_id", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
                )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, n_known long, train_tokens long, base_score double, score double")
