"""Quality classifier: a factorisation machine over hashed words, structure and metadata.

Features of a text: its words hashed to ``2**BITS`` places (square roots of counts, scaled to
unit length), binned structure statistics (one place for each statistic and bin), and binned
metadata (the stored length, if there is one). The score of features ``x`` is
``w0 + w.x + 1/2 * sum_f ((V_f.x)**2 - (V_f**2).(x**2))``: the sum-of-squares identity gives all
pairwise interactions in time linear in the non-zero features.

Training runs on a bounded sample of ``SAMPLE`` labelled rows (the first by a hash of the id),
whose sparse features alone reach the driver; scoring covers all rows and whole texts in
vectorised batches. Defined cases: null and empty texts have only structure features and get a
score like any text; rows without label or text are not learned from; several labels of one
document count by their mean (0.5 and more is 1); with no label, or one class only, the score is that class's
share (0.5 without any); repeated rows score alike; null ids are allowed.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import textkit as tk

BITS, RANK, SAMPLE = 15, 8, 8000
BINS = 12
_STATS = ("chars", "words", "upper", "digit", "mark", "blank", "line", "high", "mean_word", "distinct", "repeat", "bang", "bar", "line_words")
META = len(_STATS)
DIMS = (1 << BITS) + (len(_STATS) + 1) * BINS + 1

_CLASS = np.zeros(256, np.uint8)
_CLASS[65:91] = 1
_CLASS[48:58] = 2
for _r in ((33, 48), (58, 65), (91, 97), (123, 127)):
    _CLASS[slice(*_r)] = 3
_CLASS[[32, 9, 11, 12, 13]] = 4
_CLASS[10] = 5
_CLASS[128:] = 6


def _share_bin(x: np.ndarray) -> np.ndarray:
    """Shares to bins: 0 alone, then powers of two up to 1."""
    return np.where(x <= 0, 0, np.clip(np.floor(np.log2(np.maximum(x, 1e-9))) + BINS - 1, 1, BINS - 1)).astype(np.int64)


def _log_bin(x: np.ndarray) -> np.ndarray:
    return np.clip(np.floor(np.log2(np.maximum(x, 0) + 1) * 0.75), 0, BINS - 1).astype(np.int64)


def features(text: pa.Array, n_chars: pa.Array | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse rows ``(places, values, ptr)``."""
    raw, offs = tk.string_buffers(text)
    words, ptr = tk.hash_words(text)
    rows = len(offs) - 1
    size, n = np.diff(offs), np.diff(ptr)
    kinds = np.stack([_per_row(np.flatnonzero(_CLASS[raw] == c), offs) for c in range(7)], axis=1) if rows else np.zeros((0, 7))
    share = kinds / np.maximum(size, 1)[:, None]
    owner = np.repeat(np.arange(rows), n)
    same = _per_row(np.flatnonzero((words[1:] == words[:-1]) & (owner[1:] == owner[:-1])), ptr)
    place = (words & np.uint64((1 << BITS) - 1)).astype(np.int64)
    keys, counts = np.unique(owner * (1 << BITS) + place, return_counts=True)
    krow, kplace = keys >> BITS, keys & ((1 << BITS) - 1)
    distinct = np.bincount(krow, minlength=rows)
    bang = _per_row(np.flatnonzero(raw == 33), offs)
    bar = _per_row(np.flatnonzero(raw == 124), offs)
    lines = kinds[:, 5] + 1
    stats = np.stack(
        [
            _log_bin(size), _log_bin(n), _share_bin(share[:, 1]), _share_bin(share[:, 2]), _share_bin(share[:, 3]), _share_bin(share[:, 4]), _share_bin(share[:, 5]), _share_bin(share[:, 6]),
            np.clip((size - kinds[:, 4] - kinds[:, 5]) / np.maximum(n, 1), 0, BINS - 1).astype(np.int64),
            np.clip(np.floor(distinct / np.maximum(n, 1) * (BINS - 1)), 0, BINS - 1).astype(np.int64),
            _share_bin(same / np.maximum(n, 1)), _share_bin(bang / np.maximum(n, 1)), _share_bin(bar / np.maximum(n, 1)), _log_bin(n / lines),
        ], axis=1,
    ).astype(np.int64)
    if n_chars is None:
        meta = np.full(rows, -1, np.int64)
    else:
        got = n_chars.cast(pa.float64()).fill_null(-1).to_numpy(zero_copy_only=False)
        meta = np.where(got >= 0, _log_bin(got), -1)
    stats = np.concatenate((stats, np.where(meta >= 0, meta, 0)[:, None]), axis=1)
    splace = (1 << BITS) + np.arange(stats.shape[1]) * BINS + stats
    splace[:, -1] = np.where(meta >= 0, splace[:, -1], DIMS - 1)
    weight = np.sqrt(counts)
    norm = np.sqrt(np.bincount(krow, weights=counts, minlength=rows))
    wvalue = weight / np.maximum(norm[krow], 1)
    width = splace.shape[1]
    all_row = np.concatenate((krow, np.repeat(np.arange(rows), width)))
    order = np.argsort(all_row, kind="stable")
    places = np.concatenate((kplace, splace.ravel()))[order]
    values = np.concatenate((wvalue, np.full(rows * width, 0.3)))[order]
    out = np.zeros(rows + 1, np.int64)
    np.cumsum(distinct + width, out=out[1:])
    return places, values, out


def _per_row(at: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    return np.diff(np.searchsorted(at, ptr))


class FactorisationMachine:
    def __init__(self, bias: float, linear: np.ndarray | None = None, factors: np.ndarray | None = None):
        self.bias, self.linear, self.factors = bias, linear, factors

    def margin(self, places, values, ptr) -> np.ndarray:
        if self.linear is None:
            return np.full(len(ptr) - 1, self.bias)
        starts = ptr[:-1]
        lin = np.add.reduceat(self.linear[places] * values, starts)
        v = self.factors[places] * values[:, None]
        total = np.add.reduceat(v, starts, axis=0)
        squares = np.add.reduceat(v * v, starts, axis=0)
        return self.bias + lin + 0.5 * (total * total - squares).sum(axis=1)

    def probability(self, places, values, ptr) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(places, values, ptr), -30, 30)))


def train(places, values, ptr, y, epochs: int | None = None, rate: float = 0.1, decay: float = 1e-4, seed: int = 7) -> FactorisationMachine:
    """Adaptive-gradient descent on the logistic loss; small samples get more epochs."""
    rows = len(y)
    epochs = epochs or max(20, min(150, 64_000 // max(1, rows)))
    if not rows:
        return FactorisationMachine(0.0)
    share = float(np.mean(y))
    if share in (0.0, 1.0):
        return FactorisationMachine(30.0 if share else -30.0)
    rng = np.random.default_rng(seed)
    w, v = np.zeros(DIMS), rng.normal(0, 0.02, (DIMS, RANK))
    gw, gv = np.full(DIMS, 1e-3), np.full((DIMS, RANK), 1e-3)
    bias, gb = float(np.log(share / (1 - share))), 1e-3
    length = np.diff(ptr)
    for _ in range(epochs):
        for chunk in np.array_split(rng.permutation(rows), max(1, rows // 64)):
            n = length[chunk]
            at = np.repeat(ptr[chunk] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            p, x = places[at], values[at]
            sub = np.concatenate(([0], np.cumsum(n)))
            vx = v[p] * x[:, None]
            total = np.add.reduceat(vx, sub[:-1], axis=0)
            margin = bias + np.add.reduceat(w[p] * x, sub[:-1]) + 0.5 * (total**2 - np.add.reduceat(vx * vx, sub[:-1], axis=0)).sum(axis=1)
            err = (1 / (1 + np.exp(-np.clip(margin, -30, 30))) - y[chunk]) / len(chunk)
            e = np.repeat(err, n)
            used, inv = np.unique(p, return_inverse=True)
            dw = np.bincount(inv, weights=e * x) + decay * w[used]
            dv = np.stack([np.bincount(inv, weights=e * x * (np.repeat(total[:, f], n) - vx[:, f])) for f in range(RANK)], axis=1) + decay * v[used]
            gw[used] += dw * dw
            gv[used] += dv * dv
            w[used] -= rate * dw / np.sqrt(gw[used])
            v[used] -= rate * dv / np.sqrt(gv[used])
            db = float(err.sum())
            gb += db * db
            bias -= rate * db / gb**0.5
    return FactorisationMachine(bias, w, v)


def _rows(docs: DataFrame, *more: str) -> DataFrame:
    meta = F.col("n_chars").cast("double") if "n_chars" in docs.columns else F.lit(None).cast("double")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), meta.alias("n_chars"), *more)


def _features(batches):
    for whole in batches:
        for b in tk.sub_batches(whole, "text"):
            places, values, ptr = features(b.column("text"), b.column("n_chars"))
            p = pa.array(ptr.astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), b.column("y"), pa.ListArray.from_arrays(p, pa.array(places.astype(np.int32))), pa.ListArray.from_arrays(p, pa.array(values.astype(np.float32)))], names=["doc_id", "y", "places", "values"]
            )


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", where=None, sample: int = SAMPLE) -> FactorisationMachine:
    """Learns from at most ``sample`` labelled documents (those of ``where``, over ``doc_id``)."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("double").alias("y"))
    if where is not None:
        known = known.where(where)
    chosen = known.groupBy("doc_id").agg((F.avg("y") >= 0.5).cast("int").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    # at most `sample` rows, so the hint has a proven bound
    rows = _rows(docs.where("text is not null")).join(F.broadcast(chosen), "doc_id").select("doc_id", "y", "text", "n_chars")
    # an id's repeated rows are one example, so the driver never sees more than `sample`
    rows = rows.groupBy("doc_id").agg(F.max("y").alias("y"), F.min(F.struct("text", "n_chars")).alias("row")).select("doc_id", "y", "row.text", "row.n_chars")
    table = rows.mapInArrow(_features, "doc_id long, y int, places array<int>, values array<float>").toArrow()
    order = np.argsort(table.column("doc_id").to_numpy(), kind="stable")
    y = table.column("y").to_numpy()
    pl, vl = table.column("places").combine_chunks(), table.column("values").combine_chunks()
    places, values = np.asarray(pl.flatten()).astype(np.int64), np.asarray(vl.flatten()).astype(np.float64)
    n = np.asarray(pl.value_lengths()) if len(y) else np.zeros(0, np.int64)
    ptr = np.concatenate(([0], np.cumsum(n)))
    at = np.concatenate([np.arange(ptr[i], ptr[i + 1]) for i in order]) if len(order) else np.zeros(0, np.int64)
    return train(places[at], values[at], np.concatenate(([0], np.cumsum(n[order]))).astype(np.int64), y[order].astype(float))


def score(docs: DataFrame, model: FactorisationMachine) -> DataFrame:
    """``(doc_id, score)``, a row per row of ``docs``."""
    if model.linear is not None:
        model = FactorisationMachine(model.bias, model.linear.astype(np.float32), model.factors.astype(np.float32))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for whole in batches:
            for b in tk.sub_batches(whole, "text"):
                got = shared.value.probability(*features(b.column("text"), b.column("n_chars")))
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(got.astype(np.float64))], names=["doc_id", "score"])

    return _rows(docs).mapInArrow(run, "doc_id long, score double")
