"""Guarded writes: staged files, a verdict, then publication.

A target is a directory of versions with numbered pointer files, of which the last one counts;
the write of a version is complete before its pointer appears under its own name, so an aborted
write, at whatever moment, leaves the target as it was, and of two writers at once one fails.
Paths go through Hadoop's file system, so any store that Spark writes works."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from . import resolve
from . import expr as E
from .errors import ConcurrentWrite, PolicyViolation, SchemaMismatch


@dataclass
class WriteReport:
    table: str
    rows_in: int
    rows_written: int
    violations: dict[str, int]
    version: str


class VersionedTable:
    """A Parquet table as versioned directories and a pointer to the current one."""

    def __init__(self, spark: SparkSession, name: str, root: str):
        self.spark, self.name, self.root = spark, name, root.rstrip("/")
        self.schema = None

    def _fs(self, path: str):
        p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), p

    def _pointers(self) -> list[str]:
        fs, p = self._fs(f"{self.root}/POINTER-*")
        found = fs.globStatus(p)
        return sorted(x.getPath().getName() for x in found) if found is not None else []

    def current(self) -> list[str]:
        last = self._pointers()[-1:]
        if not last:
            return []
        fs, p = self._fs(f"{self.root}/{last[0]}")
        stream = fs.open(p)
        try:
            text = self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return [x for x in text.split("\n") if x]

    def stage(self, df: DataFrame) -> str:
        version = uuid.uuid4().hex
        df.write.parquet(f"{self.root}/{version}")
        return version

    def publish(self, versions: list[str]) -> None:
        last = self._pointers()[-1:]
        number = int(last[0].rpartition("-")[2]) + 1 if last else 0
        fs, new = self._fs(f"{self.root}/NEXT-{uuid.uuid4().hex}")
        out = fs.create(new)
        out.write(bytearray(("\n".join(versions) + "\n").encode()))
        out.close()
        _, named = self._fs(f"{self.root}/POINTER-{number:012d}")
        if fs.exists(named) or not fs.rename(new, named):
            fs.delete(new, False)
            raise ConcurrentWrite(f"{self.name}: another write was published meanwhile")

    def discard(self, version: str) -> None:
        fs, p = self._fs(f"{self.root}/{version}")
        fs.delete(p, True)

    def create(self, df: DataFrame) -> "VersionedTable":
        self.schema = df.schema
        self.publish([self.stage(df)])
        return self

    def read(self) -> DataFrame:
        return self.version(*self.current())

    def version(self, *names: str) -> DataFrame:
        reader = self.spark.read if self.schema is None else self.spark.read.schema(self.schema)
        return reader.parquet(*[f"{self.root}/{v}" for v in names])

    def register(self) -> DataFrame:
        self.read().createOrReplaceTempView(self.name)
        return self.spark.table(self.name)


def insert_into(guard, table: VersionedTable, df: DataFrame, mode: str = "append", strategy: str = "auto") -> WriteReport:
    """Writes what the policies of the sink let through. Columns map by position to the
    target's. KILL leaves the target as it was."""
    target = table.read().schema if table.current() else df.schema
    out, violations, rows_in = _let_through(guard, table, df, target, strategy)
    version = table.stage(out)
    written = table.version(version).count()
    table.publish(([] if mode == "overwrite" else table.current()) + [version])
    return WriteReport(table.name, written if rows_in is None else rows_in, written, violations, version)


def _let_through(guard, table: VersionedTable, df: DataFrame, target, strategy: str):
    """The rows that the sink's policies let through, as the target's columns (by position), the
    violations, and the number of rows before; KILL raises."""
    if len(target) != len(df.columns):
        raise SchemaMismatch(f"{table.name} has {len(target)} columns, the rows have {len(df.columns)}")
    by_sink = {f.name.lower(): c for f, c in zip(target, df.columns)}
    a, query, bound = guard.annotate(df, strategy, sink=table.name)
    violations: dict[str, int] = {}
    out, rows_in = df, None
    if a is not None:
        counts = {r["policy"]: r for r in resolve.count_violations(a, bound, by_sink).collect()}
        violations = {k: int(r["violations"]) for k, r in counts.items()}
        rows_in = int(next(iter(counts.values()))["total"])
        for b in bound:
            if b.policy.on_fail.kind == "kill" and violations.get(b.policy.name):
                raise PolicyViolation(b.policy.name, violations[b.policy.name])
        out = resolve.apply(a, list(bound), by_sink)
    out = out.toDF(*target.names)
    return out.select(*[F.col(f.name).cast(f.dataType) for f in target]), violations, rows_in


def merge_into(guard, table: VersionedTable, key: str, df: DataFrame, matched: str = "update", not_matched: str = "insert", strategy: str = "auto") -> WriteReport:
    """Copy-on-write merge of what the sink's policies let through. A row whose key the table
    holds updates or deletes it, or is passed over (``matched``: update, delete, keep); another
    row is added or passed over (``not_matched``: insert, skip). Null keys match nothing. Two rows
    of one key that the table holds are refused, as in SQL, unless they are passed over."""
    if matched not in ("update", "delete", "keep") or not_matched not in ("insert", "skip"):
        raise ValueError(f"merge: {matched}, {not_matched}")
    old = table.read()
    target = old.schema
    out, violations, rows_in = _let_through(guard, table, df, target, strategy)
    staged = table.stage(out)
    fresh = table.version(staged)
    known = old.select(F.col(key).alias("__k")).where("__k is not null").distinct()
    if matched != "keep":
        twice = fresh.join(known, F.col(key) == F.col("__k"), "left_semi").groupBy(key).count().where("count > 1").limit(1).collect()
        if twice:
            table.discard(staged)
            raise ConcurrentWrite(f"{table.name}: two rows of the source match key {twice[0][0]!r}")
    taken = fresh.select(F.col(key).alias("__k")).where("__k is not null").distinct()
    parts = [old if matched == "keep" else old.join(taken, F.col(key) == F.col("__k"), "left_anti")]
    if matched == "update":
        parts.append(fresh.join(known, F.col(key) == F.col("__k"), "left_semi"))
    if not_matched == "insert":
        parts.append(fresh.join(known, F.col(key) == F.col("__k"), "left_anti"))
    merged = parts[0]
    for p in parts[1:]:
        merged = merged.unionByName(p)
    version = table.stage(merged)
    taken_in = fresh.count()
    table.publish([version])
    table.discard(staged)
    return WriteReport(table.name, taken_in if rows_in is None else rows_in, taken_in, violations, version)


def update(guard, table: VersionedTable, key: str, set_: dict[str, Column | str] | None = None, where: Column | str | None = None, changes: DataFrame | None = None) -> WriteReport:
    """Copy-on-write update. The policies see the old version as the source ``<table>`` and the
    new one as the sink; under REMOVE a row whose change violates keeps its old version. New
    values are expressions, or come from ``changes``: rows of a key each, with columns to set."""
    spark = guard.spark
    old = table.read()
    names = old.columns
    old.createOrReplaceTempView(table.name)
    cond = F.lit(True) if where is None else (F.expr(where) if isinstance(where, str) else where)
    put = {c: (F.expr(v) if isinstance(v, str) else v) for c, v in (set_ or {}).items()}
    rows = spark.table(table.name).where(cond)
    if changes is not None:
        rows = rows.join(changes.toDF(*[f"__c_{c}" for c in changes.columns]), F.col(key) == F.col(f"__c_{key}"))
        put |= {c: F.col(f"__c_{c}") for c in changes.columns if c != key}
    changed = rows.select(*[put.get(c, F.col(c)).alias(c) for c in names])
    a, query, bound = guard.annotate(changed, "inline", sink=table.name)
    violations: dict[str, int] = {}
    passed = changed
    if a is not None:
        violations = {r["policy"]: int(r["violations"]) for r in resolve.count_violations(a, bound, {n.lower(): n for n in names}).collect()}
        for b in bound:
            if b.policy.on_fail.kind == "kill" and violations.get(b.policy.name):
                raise PolicyViolation(b.policy.name, violations[b.policy.name])
        passed = resolve.apply(a, bound, {n.lower(): n for n in names})
    fresh = passed.select(*[F.col(c).alias(f"__n_{c}") if c != key else F.col(c).alias("__k") for c in names])
    merged = old.join(fresh, F.col(key).eqNullSafe(F.col("__k")), "left")
    out = merged.select(*[F.col(c) if c == key else F.when(F.col("__k").isNotNull(), F.col(f"__n_{c}")).otherwise(F.col(c)).alias(c) for c in names])
    version = table.stage(out.select(*[F.col(f.name).cast(f.dataType) for f in old.schema]))
    total = table.version(version).count()
    table.publish([version])
    return WriteReport(table.name, total, total, violations, version)


def update_each(guard, table: VersionedTable, key: str, requests: DataFrame, column: str) -> list[WriteReport]:
    """Guarded updates ``(seq, key, column)`` as if each were one statement, in order. A statement
    touches one key, so the n-th requests of all keys are one update: as many as the key with
    most requests has. Returns a report for each."""
    order = Window.partitionBy(key).orderBy("seq")
    dealt = f"requests-{uuid.uuid4().hex}"
    path = f"{table.root}/{dealt}"
    requests.select(key, column, F.row_number().over(order).alias("__round")).write.partitionBy("__round").parquet(path)
    kept = guard.spark.read.parquet(path)
    rounds = kept.agg(F.max("__round")).first()[0] or 0
    out = [update(guard, table, key, changes=kept.where(F.col("__round") == n).select(key, column)) for n in range(1, rounds + 1)]
    table.discard(dealt)
    return out


def fold_transitions(state: DataFrame, requests: DataFrame, legal: str, key: str = "id", column: str = "state") -> DataFrame:
    """The state after all requests ``(seq, key, new_<column>)`` in order, each applied only if
    the move is legal: ``legal`` is a constraint over the names ``old`` and ``new``. One pass per
    key, equal to applying the requests one statement at a time, as a move touches one key; a
    plain check of what ``update_each`` does, without policies."""

    def put(n: E.Node) -> E.Node:
        return E.Attr(({"old": "s", "new": "m"}[n.name.lower()],)) if isinstance(n, E.Attr) and n.qualifier is None and n.name.lower() in ("old", "new") else E.rebuild(n, put)

    per = requests.groupBy(key).agg(F.expr(f"transform(array_sort(collect_list(struct(seq, new_{column}))), x -> x.new_{column})").alias("__moves"))
    step = E.render(put(E.parse(legal)))
    folded = F.expr(f"aggregate(coalesce(__moves, array()), {column}, (s, m) -> if(coalesce({step}, false), m, s))")
    return state.join(per, key, "left").select(key, folded.alias(column))


def quarantine(guard, df, strategy: str = "inline") -> DataFrame:
    """The violating rows with the names of the policies that they break (non-blocking use)."""
    a, query, bound = guard.annotate(df, strategy)
    if a is None:
        return query.df.limit(0).withColumn("policies", F.array().cast("array<string>"))
    frame, names, ok, _ = resolve.annotated_frame(a, bound)
    flat = frame.toDF(*names, *[f"__tg_z{i}" for i in range(2 * len(ok))])
    broken = F.array_compact(F.array(*[F.when(~F.coalesce(F.col(f"__tg_z{2 * i}"), F.lit(False)), F.lit(n)) for i, n in enumerate(ok)]))
    return flat.withColumn("policies", broken).where(F.size("policies") > 0).select(*names, "policies")
