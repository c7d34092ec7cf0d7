"""Near-duplicate documents by tensored MinHash banding with exact verification.

Signature. Two collections, each of ``SIDE`` groups of ``GROUP`` minhashes, are computed per
document: ``2 * SIDE * GROUP`` minhashes in all. Every pair (left group, right group) keys one
of ``SIDE * SIDE`` tables, so ``SIDE**2`` bands of ``2 * GROUP`` rows cost only the square root
of the minhash work that independent bands would. Two sets of similarity ``s`` share a table
unless no left group or no right group agrees: miss probability below
``2 * (1 - s**GROUP) ** SIDE`` (7e-5 at s = 0.8 with the defaults, 4e-8 at s = 0.9).

Search, without emitting all pairs of a group:
 1. documents with equal shingle sets form one class (pre-aggregated; copies go no further);
 2. every table bucket is covered by leaders: a member whose sketch is near its bucket's leader
    is served. Jaccard distance is a metric, so a partner (distance at most 0.2) of a served member is no farther
    from that leader than ``1 - NEAR + 0.2``: the leader's family, all bucket members within
    that distance, holds every link of the members that it serves. A bucket's unserved members
    form one more family;
 3. families join on full sets, breadth first over unvisited members, and emit only a spanning
    forest of the verified links. Large families are dealt out in pairs of blocks of bounded
    size. Connected components of the forest are the groups.

Rows are kept whole: nothing is capped, sampled or dropped. Defined cases: null text, blank
text and text without words have an empty set, n_shingles 0, and link with nothing; repeated
rows of one id are one vertex; rows with a null id come back with a null component; an empty
table gives an empty result; other columns are ignored by ``near_duplicates``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textkit as tk
from .components import components
from .state import hold, keep, release

SIDE, GROUP = 10, 2
#: Minhashes, all of which key tables.
WIDTH = 2 * SIDE * GROUP
#: Places of the sketch, which takes no minhash of its own: shingle hashes fall into bins by
#: their top bits, and each bin keeps the low byte of its smallest one (0: none).
BINS = 128
#: Share of sketch places by which a member is served by a leader, and by which it belongs to
#: the leader's family: NEAR less 0.2, each less 2.3 standard deviations of the estimate.
NEAR, FAMILY = 0.6, 0.2
#: Bytes of a stored shingle hash: two shingles of one pair of sets of a thousand agree by
#: chance once in a million pairs.
BYTES = 5
#: Shingles of a block, about.
BLOCK = 1 << 20

_A = tk.mix(np.arange(1, WIDTH + 1, dtype=np.uint64) * np.uint64(0x632BE59BD9B4E019)) | np.uint64(1)
_B = tk.mix(np.arange(1, WIDTH + 1, dtype=np.uint64) * np.uint64(0x9FB21C651E98DF25))

SIGNED = "doc_id long, n_shingles long, set_lo long, set_hi long, groups array<int>, sketch binary"


def _min_rows(values: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """Minhashes (rows x WIDTH, 32 bit) of rows that all have values."""
    out = np.empty((len(ptr) - 1, WIDTH), np.uint32)
    starts = ptr[:-1]
    for i in range(WIDTH):
        out[:, i] = np.minimum.reduceat(((values * _A[i] + _B[i]) >> np.uint64(32)).astype(np.uint32), starts)
    return out


def _bin_rows(values: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """Sketches (rows x BINS, 8 bit) of rows of sorted values."""
    row = np.repeat(np.arange(len(ptr) - 1), np.diff(ptr))
    place = row * BINS + (values >> np.uint64(64 - BINS.bit_length() + 1)).astype(np.int64)
    # values are sorted within rows, so the first of a bin is its smallest
    first = np.flatnonzero(np.concatenate(([True], place[1:] != place[:-1])))
    out = np.zeros((len(ptr) - 1) * BINS, np.uint8)
    out[place[first]] = (values[first] % np.uint64(255)).astype(np.uint8) + 1
    return out.reshape(-1, BINS)


def _sign(k: int):
    def run(batches):
        for whole in batches:
            for batch in tk.sub_batches(whole, "text"):
                words, ptr = tk.hash_words(batch.column("text"))
                sh, ptr = tk.shingles(words, ptr, k)
                n = np.diff(ptr)
                full = np.flatnonzero(n > 0)
                sizes = np.zeros(len(n), np.int64)
                lo, hi = np.zeros(len(n), np.int64), np.zeros(len(n), np.int64)
                groups = [[] for _ in n]
                sketch = [b""] * len(n)
                if len(full):
                    sets, sp = tk.distinct_sets(sh, ptr)
                    fp = np.concatenate((sp[full], sp[-1:]))
                    sizes[full] = np.diff(fp)
                    lo[full] = np.add.reduceat(tk.mix(sets + np.uint64(0x1234567)), fp[:-1]).view(np.int64)
                    hi[full] = np.add.reduceat(tk.mix(sets ^ np.uint64(0xABCDEF0123)), fp[:-1]).view(np.int64)
                    mins = _min_rows(sets, fp)
                    pairs = mins.reshape(len(full), 2 * SIDE, GROUP).astype(np.uint64)
                    g = tk.mix((pairs[:, :, 0] << np.uint64(32)) | pairs[:, :, 1])
                    for extra in range(2, GROUP):
                        g = tk.mix(g ^ pairs[:, :, extra])
                    g = (g >> np.uint64(32)).astype(np.uint32).view(np.int32)
                    low = _bin_rows(sets, fp)
                    for row, i in enumerate(full):
                        groups[i] = g[row]
                        sketch[i] = low[row].tobytes()
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").cast(pa.int64()),
                        pa.array(sizes),
                        pa.array(lo),
                        pa.array(hi),
                        pa.array(groups, pa.list_(pa.int32())),
                        pa.array(sketch, pa.binary()),
                    ],
                    names=["doc_id", "n_shingles", "set_lo", "set_hi", "groups", "sketch"],
                )

    return run


def signatures(docs: DataFrame, k: int = 5) -> DataFrame:
    """One row per document: set size, 128-bit fingerprint of the set, table groups, sketch."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_sign(k), SIGNED)


def _sets(k: int):
    def run(batches):
        for whole in batches:
            for batch in tk.sub_batches(whole, "text"):
                words, ptr = tk.hash_words(batch.column("text"))
                sh, ptr = tk.shingles(words, ptr, k)
                sets, sp = tk.distinct_sets(sh, ptr)
                raw = sets.astype("<u8").view(np.uint8).reshape(-1, 8)[:, 8 - BYTES :].tobytes()
                packed = [raw[BYTES * a : BYTES * b] for a, b in zip(sp[:-1], sp[1:])]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(sp)), pa.array(packed, pa.binary())], names=["doc_id", "n", "shingles"])

    return run


def _agree(batches):
    """Share of sketch places that agree."""
    for b in batches:
        x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint8).reshape(b.num_rows, -1) for c in ("sa", "sb"))
        # of the places that either set fills
        sim = ((x == y) & (x != 0)).sum(axis=1) / np.maximum(((x != 0) | (y != 0)).sum(axis=1), 1) if b.num_rows else np.zeros(0)
        yield pa.RecordBatch.from_arrays([b.column("lead"), b.column("id"), pa.array(sim)], names=["lead", "id", "sim"])


def _family_links(percent: int):
    """A spanning forest of the verified links of one family, or of two blocks of it."""

    def run(key, table):
        ids, side = table.column("id").to_numpy(), table.column("side").to_numpy()
        packed = table.column("shingles").to_pylist()
        ptr = np.concatenate(([0], np.cumsum([len(x) // BYTES for x in packed])))
        wide = np.zeros((int(ptr[-1]), 8), np.uint8)
        wide[:, :BYTES] = np.frombuffer(b"".join(packed), np.uint8).reshape(-1, BYTES)
        flat = wide.view("<u8").ravel()
        size = np.diff(ptr)
        _, codes = np.unique(flat, return_inverse=True)
        mark = np.zeros(len(flat) + 1, bool)
        free = np.ones(len(ids), bool)
        out_a, out_b = [], []
        for start in np.flatnonzero(side != 1):
            if not free[start]:
                continue
            free[start] = False
            queue = [int(start)]
            while queue:
                v = queue.pop()
                to = free if side[v] == 2 else free & (side != side[v])
                rest = np.flatnonzero(to)
                rest = rest[100 * np.minimum(size[rest], size[v]) >= percent * np.maximum(size[rest], size[v])]
                if not len(rest):
                    continue
                own = codes[ptr[v] : ptr[v + 1]]
                mark[own] = True
                n = size[rest]
                at = np.repeat(ptr[rest] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
                common = np.add.reduceat(mark[codes[at]].astype(np.int64), np.cumsum(n) - n)
                mark[own] = False
                new = rest[100 * common >= percent * (n + size[v] - common)]
                free[new] = False
                out_a.append(np.full(len(new), ids[v]))
                out_b.append(ids[new])
                queue.extend(new.tolist())
        cat = lambda v: np.concatenate(v) if v else np.zeros(0, np.int64)
        return pa.table({"a": cat(out_a), "b": cat(out_b)})

    return run


def classes_of(signed: DataFrame) -> DataFrame:
    """Membership: every document's class (smallest id with the same shingle set)."""
    full = signed.where("n_shingles > 0 and doc_id is not null")
    return full.groupBy("set_lo", "set_hi", "n_shingles").agg(F.min("doc_id").alias("id"), F.first("groups").alias("groups"), F.first("sketch").alias("sketch"))


def _shared(spread: DataFrame) -> DataFrame:
    """Buckets of more than one member, and the smallest id of each."""
    return spread.groupBy("key").agg(F.min("id").alias("lead"), F.max("id").alias("top")).where("lead < top").select("key", "lead")


def families(classes: DataFrame) -> DataFrame:
    """``(kind, lead, id)``: the members of every family: of a leader (kind 0, the leader
    included), or of a bucket's unserved members (kind 1, ``lead`` is the bucket's key)."""
    parts = int(classes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # the table's number stands in the low bits of its keys
    keys = F.expr(f"transform(sequence(0, {SIDE * SIDE - 1}), p -> (xxhash64(p, groups[cast(p / {SIDE} as int)], groups[{SIDE} + p % {SIDE}]) & ~1023L) | p)")
    spread = classes.select("id", "groups").repartition(parts, "id").select(F.explode(keys).alias("key"), "id")
    # leaders by a pre-aggregated minimum and a join, so that no task holds a whole bucket
    rows = hold(spread.join(_shared(spread), "key"))
    pairs = rows.where("id <> lead").select("lead", "id").distinct()
    sketches = classes.select("id", "sketch")
    both = pairs.join(sketches.withColumnRenamed("sketch", "sb"), "id").join(sketches.select(F.col("id").alias("lead"), F.col("sketch").alias("sa")), "lead")
    found = keep(both.select("lead", "id", "sa", "sb").mapInArrow(_agree, "lead long, id long, sim double").where(F.col("sim") >= FAMILY), "near-sims")
    led = found.select("lead", "id").union(found.select("lead", F.col("lead"))).toDF("lead", "id").distinct()
    open_ = rows.where("id <> lead").join(found.where(F.col("sim") >= NEAR).select("lead", "id"), ["lead", "id"], "left_anti").select("key", "id")
    rest = open_.join(_shared(open_), "key", "left_semi")
    out = led.select(F.lit(0).alias("kind"), "lead", "id").union(rest.select(F.lit(1), F.col("key"), "id"))
    out = keep(out, "near-families")
    release(rows, found)
    return out


def class_links(docs: DataFrame, classes: DataFrame, k: int, percent: int) -> DataFrame:
    """Verified links between class representatives that connect every component."""
    member = families(classes)
    wanted = member.select(F.col("id").alias("doc_id")).distinct()
    # one plan at every size: the texts are shuffled, and the ids of a partition are hashed
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(wanted.hint("shuffle_hash"), "doc_id", "left_semi")
    sets = hold(texts.mapInArrow(_sets(k), "doc_id long, n long, shingles binary").withColumnRenamed("doc_id", "id"))
    room = member.join(sets.select("id", "n"), "id").groupBy("kind", "lead").agg(F.ceil(F.sum("n") / BLOCK).cast("int").alias("blocks")).where("blocks > 1")
    room = keep(room, "near-blocks")
    work = member.join(sets.select("id", "shingles"), "id").join(room, ["kind", "lead"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    work = work.withColumn("block", F.expr("cast(pmod(xxhash64(id), blocks) as int)"))
    work = work.withColumn("other", F.explode(F.expr("sequence(0, blocks - 1)")))
    work = work.select(
        "kind", "lead", F.least("block", "other").alias("x"), F.greatest("block", "other").alias("y"), "id", "shingles",
        F.expr("case when block = other then 2 when block < other then 0 else 1 end").alias("side"),
    )
    links = keep(work.groupBy("kind", "lead", "x", "y").applyInArrow(_family_links(percent), "a long, b long").distinct(), "near-links")
    release(sets, member, room)
    return links


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """``(doc_id, n_shingles, class_id, component_id, kept)``, a row per row of ``docs``."""
    signed = hold(signatures(docs, k))
    classes = keep(classes_of(signed), "near-classes")
    links = class_links(docs, classes, k, percent)
    found = components(links)
    release(links)
    roots = classes.select("set_lo", "set_hi", "n_shingles", F.col("id").alias("class_id")).join(found.withColumnRenamed("id", "class_id"), "class_id", "left")
    roots = roots.select("set_lo", "set_hi", "n_shingles", "class_id", F.coalesce("component", "class_id").alias("component"))
    out = signed.select("doc_id", "n_shingles", "set_lo", "set_hi").join(roots, ["set_lo", "set_hi", "n_shingles"], "left")
    own = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("component")).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "n_shingles", F.coalesce("class_id", "doc_id").alias("class_id"), own.alias("component_id"), F.coalesce(own == F.col("doc_id"), F.lit(False)).alias("kept"))
    # narrow rows: written, so that all that they were made of can go
    out = keep(out, "near-groups")
    release(signed, classes, found)
    return out


def keep_one(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """Documents without those whose near-duplicate group has a smaller id; all columns kept.

    Rows with a null id stay; of rows that repeat an id one stays."""
    gone = near_duplicates(docs, k, percent).where("doc_id is not null and not kept").select(F.col("doc_id").alias("__gone"))
    named = docs.where("doc_id is not null").dropDuplicates(["doc_id"])
    left = named.join(gone.distinct(), named["doc_id"] == F.col("__gone"), "left_anti")
    return left.unionByName(docs.where("doc_id is null"))
