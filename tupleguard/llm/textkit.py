"""Vectorised text primitives shared by the corpus operators.

Everything here works on Arrow string arrays inside ``mapInArrow`` tasks: texts are
handled as one byte buffer per chunk, so cost per byte is a few numpy passes and memory
is bounded by ``CHUNK`` bytes of text times a small factor, whatever the document sizes.

Words are maximal runs of bytes other than ASCII space and 0x09-0x0D, with A-Z lowered,
so they equal the pattern ``[^\\x20\\x09-\\x0D]+`` over the UTF-8 text.
"""

from __future__ import annotations

from typing import Iterator

import numpy as np
import pyarrow as pa

CHUNK = 1 << 21
U = np.uint64
_P = U(0x9E3779B97F4A7C15)
_PINV = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective)."""
    x = np.asarray(x, dtype=U).copy()
    x ^= x >> U(33)
    x *= U(0xFF51AFD7ED558CCD)
    x ^= x >> U(33)
    x *= U(0xC4CEB9FE1A85EC53)
    x ^= x >> U(33)
    return x


_BYTE = mix(np.arange(1, 257, dtype=U) * U(0xD6E8FEB86659FD93))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BYTE_LOWER = _BYTE[_LOWER]
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_POWERS: dict[str, np.ndarray] = {}


def _powers(name: str, base: np.uint64, n: int) -> np.ndarray:
    have = _POWERS.get(name)
    if have is None or len(have) < n:
        size = max(n, CHUNK + 1)
        table = np.full(size, base, dtype=U)
        table[0] = 1
        have = np.multiply.accumulate(table)
        if size <= 4 * CHUNK:
            _POWERS[name] = have
    return have[:n]


def string_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offs, data = column.buffers()
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(offs, dtype=np.int64, count=column.offset + n + 1)[column.offset :]
    first = int(offsets[0])
    size = int(offsets[-1]) - first
    raw = np.frombuffer(data, dtype=np.uint8, count=first + size)[first:] if data is not None and size else np.zeros(0, np.uint8)
    return raw, offsets - first


def _pieces(raw: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[np.ndarray, int, int]]:
    """Chunks (bytes, first document, end document), each of whole documents, or a part of one
    long document that ends at white space."""
    n, at = len(offsets) - 1, 0
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + CHUNK, side="right")) - 1
        if end > at:
            yield raw[offsets[at] : offsets[end]], at, end
            at = end
            continue
        start, stop = int(offsets[at]), int(offsets[at + 1])
        while stop - start > CHUNK:
            cut = start + CHUNK
            while cut < stop:
                here = np.flatnonzero(_SPACE[raw[cut : cut + CHUNK]])
                if len(here):
                    cut += int(here[0])
                    break
                cut += CHUNK
            cut = min(cut, stop)
            yield raw[start:cut], at, at + 1
            start = cut
        yield raw[start:stop], at, at + 1
        at += 1


def hash_words(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the lower-cased words of each row, and where each row's begin.

    Returns ``(hashes, ptr)``; row ``i`` has ``hashes[ptr[i]:ptr[i+1]]``. Null and blank rows
    have none."""
    raw, offsets = string_buffers(column)
    n = len(offsets) - 1
    counts = np.zeros(n, np.int64)
    out: list[np.ndarray] = []
    for piece, lo, hi in _pieces(raw, offsets):
        size = len(piece)
        if not size:
            continue
        gap = np.ones(size + 2, dtype=bool)
        gap[1:-1] = _SPACE[piece]
        word = ~gap
        starts_mask = word[1:-1] & gap[:-2]
        inner = offsets[lo + 1 : hi] - offsets[lo] if hi - lo > 1 else np.zeros(0, np.int64)
        inner = inner[(inner > 0) & (inner < size)]
        starts_mask[inner] |= word[1:-1][inner]
        ends_mask = word[1:-1] & gap[2:]
        ends_mask[inner - 1] |= word[1:-1][inner - 1]
        starts, ends = np.flatnonzero(starts_mask), np.flatnonzero(ends_mask)
        if not len(starts):
            continue
        acc = _BYTE_LOWER[piece]
        acc *= _powers("p", _P, size)
        np.cumsum(acc, out=acc)
        value = acc[ends]
        before = starts > 0
        value[before] -= acc[starts[before] - 1]
        value *= _powers("i", _PINV, size)[starts]
        value += (ends - starts).astype(U) * U(0x2545F4914F6CDD1D)
        out.append(mix(value))
        if hi - lo == 1:
            counts[lo] += len(starts)
        else:
            edges = np.searchsorted(starts, offsets[lo : hi + 1] - offsets[lo])
            counts[lo:hi] += np.diff(edges)
    ptr = np.zeros(n + 1, np.int64)
    np.cumsum(counts, out=ptr[1:])
    return (np.concatenate(out) if out else np.zeros(0, U)), ptr


def hash_word(word: str) -> int:
    """The hash that ``hash_words`` gives this one word."""
    return int(hash_words(pa.array([word]))[0][0])


def shingles(words: np.ndarray, ptr: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of ``k`` words; a row with 1 to k-1 words has one, of the whole row.

    Rows keep repeats; returns ``(hashes, ptr)``."""
    n = np.diff(ptr)
    counts = np.where(n >= k, n - k + 1, (n > 0).astype(np.int64))
    out_ptr = np.zeros(len(ptr), np.int64)
    np.cumsum(counts, out=out_ptr[1:])
    if not len(words):
        return np.zeros(0, U), out_ptr
    mult = mix(np.arange(1, k + 1, dtype=U) * U(0xA0761D6478BD642F)) | U(1)
    total = len(words)
    acc = np.zeros(total, U)
    for j in range(min(k, total)):
        acc[: total - j] += words[j:] * mult[j]
    acc = mix(acc + U(k))
    full = np.flatnonzero(n >= k)
    short = np.flatnonzero((n > 0) & (n < k))
    res = np.zeros(int(out_ptr[-1]), U)
    if len(full):
        lengths = counts[full]
        src = np.repeat(ptr[full] - np.concatenate(([0], np.cumsum(lengths)[:-1])), lengths) + np.arange(int(lengths.sum()))
        dst = np.repeat(out_ptr[full] - np.concatenate(([0], np.cumsum(lengths)[:-1])), lengths) + np.arange(int(lengths.sum()))
        res[dst] = acc[src]
    for i in short:
        w = words[ptr[i] : ptr[i + 1]]
        res[out_ptr[i]] = mix(np.array([(w * mult[: len(w)]).sum(dtype=U) + U(len(w)) + U(0x51ED27)], U))[0]
    return res, out_ptr


def distinct_sets(hashes: np.ndarray, ptr: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each row."""
    parts, counts = [], np.zeros(len(ptr) - 1, np.int64)
    for i in range(len(ptr) - 1):
        if ptr[i + 1] > ptr[i]:
            got = np.unique(hashes[ptr[i] : ptr[i + 1]])
            counts[i] = len(got)
            parts.append(got)
    out = np.zeros(len(ptr), np.int64)
    np.cumsum(counts, out=out[1:])
    return (np.concatenate(parts) if parts else np.zeros(0, U)), out


def long_lists(values: np.ndarray, ptr: np.ndarray) -> pa.Array:
    """A list<int64> column of unsigned values (bit pattern kept)."""
    return pa.ListArray.from_arrays(pa.array(ptr.astype(np.int32)), pa.array(values.view(np.int64)))


def crc_mod(name: str, m: int):
    """Column: crc32 of the id as text, modulo m; null ids count as the text ''."""
    from pyspark.sql import functions as F

    return F.crc32(F.encode(F.coalesce(F.col(name).cast("string"), F.lit("")), "UTF-8")) % m


def sub_batches(batch: pa.RecordBatch, column: str, limit: int = 4 * CHUNK) -> Iterator[pa.RecordBatch]:
    """Slices of the batch of about ``limit`` bytes of text each, one row at least."""
    _, offsets = string_buffers(batch.column(batch.schema.get_field_index(column)))
    n, at = batch.num_rows, 0
    while at < n:
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1)
        yield batch.slice(at, end - at)
        at = end
