"""Near-duplicate vectors: an exact metric range join on the unit sphere.

Cosine at least ``c`` between unit vectors is Euclidean distance at most
``r = sqrt(2 - 2c)``. Pivots, in number proportional to a label's vectors, cut them into cells
(nearest pivot). By the triangle inequality a partner of ``x`` can lie in cell ``j`` only if
``d(x, p_j) <= radius_j + r`` and ``d(x, p_j) - d(x, p_own) <= 2 r``; ``x`` visits only such
cells (of a higher number, so that each pair meets once), and the cells then join independently
by matrix products. The members of a cell and its visitors are dealt out in blocks, so no task
holds more than two blocks. Pivots decide only where work is done, never which links exist.

Pivots come from a sample of ``SAMPLE`` vectors of all labels (a bounded number goes to the
driver); labels without any have one cell. They are first met ones by hash, so that cells are
of about equal weight: a cell is meant to hold ``CELL`` vectors.

Exact copies are joined first (one class per label and vector, with its count) and are counted,
not compared. Of each block only per-class counts and a spanning forest leave the task, so
rows out stay proportional to rows in.

Defined cases: a null label, null or empty vector, a zero vector and one with null, NaN or
infinite components link with nothing; vectors of unlike length under one label never link;
repeated rows of an id count as vectors of their own in ``n_links`` (each row has the links of
its own label and vector) but are one vertex; rows with a null id link with nothing and are
returned; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .components import components
from .state import keep, release

#: Vectors, at most, that pivots are taken from, and vectors that a cell is meant to hold. A
#: sampled label keeps at least ``SPARE`` sampled vectors for each of its pivots.
SAMPLE, CELL, SPARE = 16_384, 512, 2
#: Vectors of a block.
BLOCK = 2048
#: Slack of distances for rounding; cosines are compared without any.
EPS = 1e-9


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _choose_pivots(sample: list, members: dict) -> dict:
    """Pivots for each (label, dimension): the first of its sample, in hash order."""
    by: dict = {}
    for label, vec in sample:
        by.setdefault((label, len(vec)), []).append(vec)
    return {key: _unit(np.asarray(vecs[: max(1, min(len(vecs) // SPARE, members.get(key, 0) // CELL))], np.float64)) for key, vecs in by.items()}


def _distances(pivots: dict, label, v) -> np.ndarray | None:
    p = pivots.get((label, len(v)))
    if p is None or len(p) == 1:
        return None
    v = np.asarray(v, np.float64)
    return np.linalg.norm(p - v / np.linalg.norm(v), axis=1)


def _cell(pivots: dict):
    """Own cell of each vector and its distance from the cell's pivot."""

    def run(batches):
        for b in batches:
            cell, near = [], []
            for label, v in zip(b.column("label").to_pylist(), b.column("vec").to_pylist()):
                d = _distances(pivots, label, v)
                cell.append(0 if d is None else int(d.argmin()))
                near.append(0.0 if d is None else float(d.min()))
            yield pa.RecordBatch.from_arrays([b.column("label"), pa.array([len(v) for v in b.column("vec").to_pylist()], pa.int32()), pa.array(cell, pa.int32()), pa.array(near)], names=["label", "dim", "cell", "near"])

    return run


def _place(pivots: dict, radii: dict, r: float):
    """Own cell and the higher cells that may hold partners."""

    def run(batches):
        for b in batches:
            cell, reach = [], []
            for label, v in zip(b.column("label").to_pylist(), b.column("vec").to_pylist()):
                d = _distances(pivots, label, v)
                if d is None:
                    cell.append(0)
                    reach.append([])
                    continue
                own = int(d.argmin())
                to = (d <= radii[label, len(v)] + r) & (d - d[own] <= 2 * r)
                to[: own + 1] = False
                cell.append(own)
                reach.append(np.flatnonzero(to).tolist())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell, pa.int32()), pa.array(reach, pa.list_(pa.int32()))], names=[*b.schema.names, "cell", "reach"])

    return run


def _forest(ids: np.ndarray, linked: np.ndarray, other: np.ndarray) -> tuple[list, list]:
    """Links of a spanning forest of a bipartite block; breadth first over unvisited vertices."""
    a, b = [], []
    left_free, right_free = np.ones(len(ids), bool), np.ones(len(other), bool)
    for start in range(len(ids)):
        if not left_free[start] or not linked[start].any():
            continue
        left_free[start] = False
        queue = [(0, start)]
        while queue:
            side, v = queue.pop()
            if side == 0:
                new = np.flatnonzero(linked[v] & right_free)
                right_free[new] = False
                a.extend([ids[v]] * len(new))
                b.extend(other[new])
                queue.extend((1, int(i)) for i in new)
            else:
                new = np.flatnonzero(linked[:, v] & left_free)
                left_free[new] = False
                a.extend(ids[new])
                b.extend([other[v]] * len(new))
                queue.extend((0, int(i)) for i in new)
    return a, b


def _join_block(cosine: float):
    def run(key, table):
        side = table.column("side").to_numpy()
        ids, classes, copies = (table.column(c).to_numpy() for c in ("id", "class", "copies"))
        flat = np.asarray(table.column("vec").combine_chunks().flatten(), dtype=np.float64)
        x = flat.reshape(len(ids), -1)
        norm = np.sqrt((x * x).sum(axis=1))
        out_id, out_n, out_to = [], [], []
        if (side == 2).any():
            left = right = np.flatnonzero(side == 2)
        else:
            left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        if len(left) and len(right):
            linked = (x[left] @ x[right].T) / (norm[left][:, None] * norm[right][None, :]) >= cosine
            if left is right:
                np.fill_diagonal(linked, False)
            n_left = linked @ copies[right]
            got = np.flatnonzero(n_left)
            out_id.append(classes[left][got])
            out_n.append(n_left[got])
            if left is not right:
                n_right = copies[left] @ linked
                got = np.flatnonzero(n_right)
                out_id.append(classes[right][got])
                out_n.append(n_right[got])
            out_to = [np.full(len(v), -1, np.int64) for v in out_id]
            a, b = _forest(ids[left], linked, ids[right])
            keep_ = [(u, v) for u, v in zip(a, b) if u != v]
            out_id.append(np.array([u for u, _ in keep_], np.int64))
            out_to.append(np.array([v for _, v in keep_], np.int64))
            out_n.append(np.full(len(keep_), -1, np.int64))
        cat = lambda v: np.concatenate(v).astype(np.int64) if v else np.zeros(0, np.int64)
        return pa.table({"id": cat(out_id), "n": cat(out_n), "to": cat(out_to)})

    return run


def vector_groups(vectors: DataFrame, cosine: float = 0.93, vec: str = "embedding") -> DataFrame:
    """``(vec_id, n_links, component_id, kept)``, a row per row of ``vectors``."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("id"), F.col("label"), F.col(vec).cast("array<double>").alias("vec"))
    usable = F.expr(
        "id is not null and label is not null and vec is not null and size(vec) > 0"
        " and forall(vec, v -> v is not null and not isnan(v) and abs(v) < double('infinity')) and exists(vec, v -> v <> 0)"
    )
    usable = F.coalesce(usable, F.lit(False))
    # an id's rows with unlike labels or vectors are separate classes that share the vertex
    found_ = rows.where(usable).groupBy("label", "vec").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies"))
    classes = keep(found_.withColumn("class", F.monotonically_increasing_id()), "vec-classes")
    sample = classes.select("label", "vec").orderBy(F.xxhash64("id", "label", "vec"), "class").limit(SAMPLE).collect()
    # of the sampled labels only, so at most a row for each sampled vector
    sampled = {(r["label"], len(r["vec"])) for r in sample}
    held = classes.groupBy("label", F.size("vec").alias("dim")).agg(F.count(F.lit(1)).alias("members")).where(f"members >= {2 * CELL}")
    members = {(r["label"], r["dim"]): r["members"] for r in held.orderBy(F.desc("members")).limit(SAMPLE).collect()}
    pivots = _choose_pivots([(r["label"], r["vec"]) for r in sample], {k: members.get(k, 0) for k in sampled})
    pivots = {k: p for k, p in pivots.items() if len(p) > 1}
    label_type = classes.schema["label"].dataType.simpleString()
    radii: dict = {}
    if pivots:
        # one row a pivot
        near = classes.select("label", "vec").mapInArrow(_cell(pivots), f"label {label_type}, dim int, cell int, near double")
        for x in near.where("near > 0 or cell > 0").groupBy("label", "dim", "cell").agg(F.max("near").alias("radius")).collect():
            if (x["label"], x["dim"]) in pivots:
                radii.setdefault((x["label"], x["dim"]), np.zeros(len(pivots[x["label"], x["dim"]])))[x["cell"]] = x["radius"]
        for k, p in pivots.items():
            radii.setdefault(k, np.zeros(len(p)))
    r = math.sqrt(2 - 2 * cosine) + EPS
    shape = f"class long, id long, label {label_type}, vec array<double>, copies long, cell int, reach array<int>"
    placed = keep(classes.select("class", "id", "label", "vec", "copies").mapInArrow(_place(pivots, radii, r), shape), "vec-placed")
    at = placed.withColumn("dim", F.size("vec"))
    hosts = at.groupBy("label", "dim", "cell").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("hosts"))
    guests = at.select("label", "dim", F.explode("reach").alias("cell")).groupBy("label", "dim", "cell").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("guests"))
    layout = keep(hosts.join(guests, ["label", "dim", "cell"], "left").na.fill(0, ["guests"]), "vec-layout")
    slim = ["label", "dim", "class", "id", "vec", "copies"]
    # a class's block is one of its hash, at home and as a guest
    block = lambda n: F.expr(f"cast(pmod(xxhash64(class), {n}) as int)")
    home = at.select(*slim, "cell").join(layout, ["label", "dim", "cell"])
    own = home.withColumn("block", block("hosts")).withColumn("o", F.explode(F.expr("sequence(0, hosts - 1)")))
    own = own.select(*slim, "cell", F.lit(0).alias("visit"), F.least("block", "o").alias("x"), F.greatest("block", "o").alias("y"), F.expr("case when block = o then 2 when block < o then 0 else 1 end").alias("side"))
    met = home.where("guests > 0").withColumn("x", F.explode(F.expr("sequence(0, guests - 1)"))).select(*slim, "cell", F.lit(1).alias("visit"), "x", block("hosts").alias("y"), F.lit(1).alias("side"))
    guest = at.select(*slim, F.explode("reach").alias("cell")).join(layout, ["label", "dim", "cell"])
    guest = guest.withColumn("y", F.explode(F.expr("sequence(0, hosts - 1)"))).select(*slim, "cell", F.lit(1).alias("visit"), block("guests").alias("x"), "y", F.lit(0).alias("side"))
    work = own.union(met).union(guest)
    found = keep(work.groupBy("label", "dim", "cell", "visit", "x", "y").applyInArrow(_join_block(cosine), "id long, n long, to long"), "vec-found")
    counts = found.where("n >= 0").groupBy(F.col("id").alias("class")).agg(F.sum("n").alias("n"))
    named = classes.select("label", "vec", "class", F.col("id").alias("class_id"), "copies")
    comp = components(found.where("n < 0").select(F.col("id").alias("a"), F.col("to").alias("b")).union(
        rows.where(usable).join(named, ["label", "vec"]).where("id <> class_id").select("id", "class_id")
    ))
    member = rows.withColumn("ok", usable).join(named.withColumn("ok", F.lit(True)), ["label", "vec", "ok"], "left").select("id", "class", "copies")
    out = member.join(counts, "class", "left").join(comp, "id", "left")
    component = F.coalesce("component", "id")
    out = out.select(F.col("id").alias("vec_id"), F.coalesce(F.coalesce("n", F.lit(0)) + F.col("copies") - 1, F.lit(0)).alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(False)).alias("kept"))
    out = keep(out, "vec-groups")
    release(classes, placed, layout, found, comp)
    return out
