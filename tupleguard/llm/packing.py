"""Sequence packing by bound-certified best-fit decreasing.

Documents become pieces of at most ``capacity`` tokens (only longer documents are cut; the
first piece takes the remainder). Pieces are dealt by a hash to partitions of bounded size,
each packed by best-fit decreasing in linear time over a capacity-indexed bin list. A lower
bound from dual-feasible functions (the rounding family ``u_k`` and the threshold family
``f_eps``) certifies every partition: where it equals the bin count, packing is optimal and
final. Partitions with a gap keep their exactly full bins and give the pieces of all other
bins up for exchange: these are dealt anew among fewer partitions and packed again, until no
gap remains or a round saves no bin.

Token ids are those of the byte-level BPE file through ``tokenizers``; the same vocabulary's
rank file gives identical ids several times faster and is used where no special token's text
occurs, else the tokenizer itself.

Defined cases: null and empty texts are one piece holding only the end id; repeated rows are
packed once each; an empty table gives no rows; null ids are packed like others; other columns
are ignored.
"""

from __future__ import annotations

import base64
import itertools
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textkit as tk
from .state import keep

#: Pieces that one partition packs, at most about.
PART = 65_536
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def encoder(vocabulary_json: str, vocabulary_ranks: str | None = None, pattern: str | None = None):
    """``texts -> list of id lists`` for a byte-level BPE file of ``tokenizers``."""
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(vocabulary_json)
    special = [t.content for t in slow.get_added_tokens_decoder().values()]
    if not vocabulary_ranks:
        return lambda texts: [e.ids for e in slow.encode_batch(texts, add_special_tokens=False)]
    import tiktoken

    with open(vocabulary_ranks, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding("byte_bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def encode(texts):
        return [slow.encode(t, add_special_tokens=False).ids if any(s in t for s in special) else fast.encode_ordinary(t) for t in texts]

    return encode


def public_files() -> dict:
    """The vocabulary installed with the public tokenizers."""
    import public_tokenizers as p

    return {"vocabulary_json": p.path("byte_bpe_50k.json"), "vocabulary_ranks": p.path("byte_bpe_50k.tiktoken"), "pattern": p.PATTERN}


def _cut(files: dict | None, capacity: int, end_id: int):
    def run(batches):
        encode = encoder(**(files or public_files()))
        for whole in batches:
            for b in tk.sub_batches(whole, "text", 1 << 20):
                ids = b.column("doc_id").to_pylist()
                out = ([], [], [], [], [])
                for doc, got in zip(ids, encode([t or "" for t in b.column("text").to_pylist()])):
                    arr = np.append(np.asarray(got, dtype="<u4"), np.uint32(end_id)).astype("<u4")
                    n = len(arr)
                    first = n if n <= capacity else (n % capacity or capacity)
                    start, piece = 0, 0
                    while start < n:
                        stop = first if start == 0 else start + capacity
                        for col, v in zip(out, (doc, piece, start, stop - start, zlib.crc32(arr[start:stop].tobytes()))):
                            col.append(v)
                        start, piece = stop, piece + 1
                yield pa.RecordBatch.from_arrays(
                    [pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32())] + [pa.array(c, pa.int64()) for c in out[2:]],
                    names=["doc_id", "piece", "start", "length", "ids_crc32"],
                )

    return run


def pieces(docs: DataFrame, capacity: int = 1024, files: dict | None = None, end_id: int = 2) -> DataFrame:
    """One row per piece of every document."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_cut(files, capacity, end_id), PIECES)


def lower_bound(sizes: np.ndarray, capacity: int) -> int:
    """Bins that any packing needs at least: the best of the dual-feasible functions."""
    count = np.bincount(sizes, minlength=capacity + 1)[: capacity + 1].astype(np.int64)
    size = np.arange(capacity + 1, dtype=np.int64)
    best = -(-int((count * size).sum()) // capacity)
    # threshold family: below eps nothing, above capacity - eps a whole bin
    tail, mass = np.cumsum(count[::-1])[::-1], np.cumsum(count * size)
    for eps in range(1, capacity // 2 + 1):
        whole = int(tail[capacity - eps + 1]) if capacity - eps + 1 <= capacity else 0
        part = int(mass[capacity - eps] - mass[eps - 1])
        best = max(best, whole - (-part // capacity))
    # rounding family: x (k + 1) / C integral keeps x, else rounds down to a multiple of 1 / k
    for k in range(1, 101):
        scaled = size * (k + 1)
        exact = scaled % capacity == 0
        total_exact = int((count * size)[exact].sum())
        total_round = int((count * (scaled // capacity))[~exact].sum())
        best = max(best, -(-(total_exact * k + total_round * capacity) // (capacity * k)))
    return best


def best_fit_decreasing(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, int]:
    """The bin of each size, and the number of bins; ties go to the latest bin of that room."""
    order = np.argsort(-sizes, kind="stable")
    where = np.empty(len(sizes), np.int64)
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms, bins = 0, 0  # rooms: bit r set if a bin with room r exists
    sizes_list = sizes[order].tolist()
    placed = []
    for s in sizes_list:
        fit = rooms >> s
        if fit:
            r = s + ((fit & -fit).bit_length() - 1)
            bin_ = by_room[r].pop()
            if not by_room[r]:
                rooms &= ~(1 << r)
        else:
            r, bin_ = capacity, bins
            bins += 1
        placed.append(bin_)
        left = r - s
        if left:
            by_room[left].append(bin_)
            rooms |= 1 << left
    where[order] = placed
    return where, bins


PACKED = PIECES + ", part int, bin long, offset long, bin_length long, bins long, bound long"


def _pack(capacity: int):
    def run(key, table):
        sizes = table.column("length").to_numpy()
        where, bins = best_fit_decreasing(sizes, capacity)
        bound = lower_bound(sizes, capacity)
        order = np.argsort(where, kind="stable")
        fill = np.bincount(where, weights=sizes, minlength=bins).astype(np.int64)
        run_sum = np.cumsum(sizes[order]) - sizes[order]
        starts = np.searchsorted(where[order], np.arange(bins))
        offset = np.empty(len(sizes), np.int64)
        offset[order] = run_sum - run_sum[starts][where[order]]
        n = len(sizes)
        cols = [table.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32", "part")]
        cols += [pa.array(where), pa.array(offset), pa.array(fill[where]), pa.array(np.full(n, bins)), pa.array(np.full(n, bound))]
        return pa.table(cols, names=["doc_id", "piece", "start", "length", "ids_crc32", "part", "bin", "offset", "bin_length", "bins", "bound"])

    return run


def pack(items: DataFrame, capacity: int = 1024, part: int = PART) -> DataFrame:
    """Pieces with ``sequence_id``, ``offset`` and the certificate of their partition:
    ``round``, ``bins``, ``bound``, ``gap``."""
    cols = ["doc_id", "piece", "start", "length", "ids_crc32"]
    todo = keep(items.select(*cols), "pack-pieces", None)
    n = todo.count()
    total = None
    done: DataFrame | None = None
    for r in itertools.count():
        parts = max(1, -(-n // part))
        # the place in the stored table tells rows without an id, or of one id, apart
        dealt = todo.withColumn("part", F.expr(f"cast(pmod(xxhash64(doc_id, piece, start, monotonically_increasing_id(), {r}), {parts}) as int)"))
        packed = keep(dealt.groupBy("part").applyInArrow(_pack(capacity), PACKED), "pack-round", 4)
        packed = packed.withColumn("round", F.lit(r))
        facts = packed.groupBy("part").agg(F.first("bins").alias("bins"), F.first("bound").alias("bound")).agg(
            F.sum("bins").alias("bins"), F.sum(F.expr("bins - bound")).alias("gap"), F.count_if(F.expr("bins > bound")).alias("open")
        ).first()
        bins, gap, open_ = (facts["bins"] or 0), (facts["gap"] or 0), facts["open"]
        if total is not None and bins >= total:
            # the exchange saved nothing: the former packing of these pieces stays
            done = done.union(before) if done is not None else before
            return _numbered(done)
        if not gap or (open_ <= 1 and parts <= 1):
            done = done.union(packed) if done is not None else packed
            return _numbered(done)
        final = F.expr(f"bins <= bound or bin_length = {capacity}")
        done = done.union(packed.where(final)) if done is not None else packed.where(final)
        before = packed.where(~final)
        todo = before.select(*cols)
        left = before.select("part", "bin").distinct().agg(F.count(F.lit(1)).alias("bins")).first()
        total, n = left["bins"], todo.count()
        if not n:
            return _numbered(done)


def _numbered(packed: DataFrame) -> DataFrame:
    # a partition has less than 2**20 bins, and rounds end long before 2**11
    wide = F.expr("(cast(round as bigint) << 52) | (cast(part as bigint) << 20) | bin")
    return packed.select(
        "doc_id", "piece", "start", "length", "ids_crc32", wide.alias("sequence_id"), "offset", "round", "bins", "bound", F.expr("bins - bound").alias("gap")
    )


def pack_documents(docs: DataFrame, capacity: int = 1024, files: dict | None = None, end_id: int = 2) -> DataFrame:
    return pack(pieces(docs, capacity, files, end_id), capacity)
