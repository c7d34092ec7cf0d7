"""WARC archives: a deduplicating writer and a splittable reader.

Writer. Every row becomes one record, one gzip member each, so members can be decoded on their
own. Rows with equal payloads are found by digest over narrow rows (pre-aggregated minimum), so
a common payload gathers only ids in one place; payloads are dealt by page. The smallest id is written as ``response``, the others as ``revisit`` records that carry the
full payload's digest and length and name the record they refer to. Each task writes one file
under a name of its own attempt in the given folder (any URI that ``pyarrow.fs`` opens; by
default the session's shared folder) and reports it in a manifest; only files of the manifest
are read, so retried tasks leave no double records. The manifest also marks where the first
member at or after every ``MARK`` bytes begins.

Reader. Files are cut into byte ranges, one task row each, whatever the members' borders. A
task scans its range for the gzip magic, accepts a candidate only if it inflates to a WARC
version line and a complete header, and owns exactly the records whose first byte lies in its
range, reading past the range's end to finish the last. After an accepted member the next one
starts where it ended. The first candidate of a range must also be the member that follows from
the manifest's mark, so magic bytes inside a payload, archives within archives included, are
never taken for records. A foreign file has no marks: there a candidate's members are followed
to the range's end, and a chain that breaks off is dropped as a payload's content.

Defined cases: a null payload is empty; repeated rows of the smallest id are all responses;
null ids are written and read back as null, and lose to any id; empty tables write and read
nothing; payloads may hold any bytes, magic numbers included.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from .state import packed, shared_path

#: Bytes of a read range.
RANGE = 8 << 20
#: Distance of the manifest's marks (8 bytes each).
MARK = 8 << 20
#: Tasks that read, at most.
RANGES = 100_000
#: Bytes fetched at once.
FETCH = 1 << 20
MAGIC = b"\x1f\x8b\x08"
RECORD = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def _open_fs(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1))


def digest_of(payload: bytes) -> str:
    """SHA-1 in bare upper-case base32."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _name(page_id) -> str:
    return "<urn:page:none>" if page_id is None else f"<urn:page:{page_id}>"


def _page(name: str | None):
    tail = (name or "").strip("<>").rpartition(":")[2]
    return int(tail) if tail.lstrip("-").isdigit() else None


def record_bytes(page_id, url, payload: bytes, revisit: bool, refers_to=None, date: str = "1970-01-01T00:00:00Z") -> bytes:
    """One WARC/1.1 record."""
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: {_name(page_id)}",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {quote(url or '', safe='%/:=&?~#+!$,;@()*[]')}",
        f"WARC-Payload-Digest: sha1:{digest_of(payload)}",
        f"X-Payload-Length: {len(payload)}",
        "Content-Type: application/octet-stream",
    ]
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {_name(refers_to)}"]
    body = b"" if revisit else payload
    return "\r\n".join([*head, f"Content-Length: {len(body)}", "", ""]).encode() + body + b"\r\n\r\n"


def gzip_member(data: bytes, level: int = 6) -> bytes:
    squeeze = zlib.compressobj(level, zlib.DEFLATED, 31)
    return squeeze.compress(data) + squeeze.flush()


def _write(folder: str):
    def run(batches):
        out, total, path, filesystem, marks = None, 0, None, None, []
        for b in batches:
            if not b.num_rows:
                continue
            if out is None:
                filesystem, root = _open_fs(folder)
                filesystem.create_dir(root, recursive=True)
                path = f"part-{uuid.uuid4().hex}.warc.gz"
                out = filesystem.open_output_stream(f"{root}/{path}", compression=None)
            for page, url, html, refers in zip(*(b.column(c).to_pylist() for c in ("page_id", "url", "payload", "refers_to"))):
                member = gzip_member(record_bytes(page, url, html or b"", refers is not None, refers))
                out.write(member)
                # the first member at or after each mark
                marks += [total] * (total // MARK + 1 - len(marks))
                total += len(member)
        if out is not None:
            out.close()
            marks += [total] * (total // MARK + 1 - len(marks))
            yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([total]), pa.array([marks], pa.list_(pa.int64()))], names=["file", "size", "marks"])

    return run


def write_archives(pages: DataFrame, folder: str, payload: str = "html", least: int = 0) -> DataFrame:
    """Writes the archives and returns their manifest ``(file, size, marks)``: a row per file, of which
    there are as many as writing tasks; the driver holds it as it holds any commit's file list.

    Payloads of fewer than ``least`` bytes are never replaced by revisits."""
    rows = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col(payload).cast("binary"), F.lit(b"").cast("binary")).alias("payload")
    ).withColumn("digest", F.concat(F.sha1("payload"), F.lit(":"), F.octet_length("payload")))
    ids = rows.select("page_id", "digest", (F.octet_length("payload") >= least).alias("long"))
    first = ids.groupBy("digest").agg(F.min("page_id").alias("first_id"))
    later = F.coalesce(F.col("page_id") != F.col("first_id"), F.col("first_id").isNotNull())
    refers = ids.join(first, "digest").where(F.col("long") & later).select(F.col("page_id").alias("__page"), F.col("digest").alias("__digest"), F.col("first_id").alias("refers_to")).distinct()
    joined = rows.join(refers, F.col("page_id").eqNullSafe(F.col("__page")) & (F.col("digest") == F.col("__digest")), "left")
    joined = joined.select("page_id", "url", "payload", "refers_to")
    shape = "file string, size long, marks array<long>"
    written = packed(joined, 8).mapInArrow(_write(folder), shape).collect()
    return pages.sparkSession.createDataFrame(written, shape)


class _Window:
    """Forward reads of a file with a small buffer."""

    def __init__(self, handle, size: int, at: int):
        self.handle, self.size, self.base, self.data = handle, size, at, b""

    def need(self, at: int, n: int) -> bytes:
        """Bytes ``at .. at+n`` (fewer at the end of the file); ``at`` may only move on, or
        back within what is still held."""
        if at < self.base or at > self.base + len(self.data):
            self.base, self.data = at, b""
        end = self.base + len(self.data)
        if at + n > end and end < self.size:
            self.handle.seek(end)
            self.data += self.handle.read(max(FETCH, at + n - end))
        return self.data[at - self.base : at - self.base + n]

    def drop(self, at: int) -> None:
        if at > self.base:
            self.data, self.base = self.data[at - self.base :], max(at, self.base)


def _member(window: _Window, at: int, whole: bool):
    """Inflates the member at ``at``: (bytes, end), or None if it isn't a WARC record's. With
    ``whole`` false only the header is asked for and the end is None."""
    inflate, out, pos = zlib.decompressobj(31), [], at
    got, checked = 0, False
    try:
        while not inflate.eof:
            step = window.need(pos, 1 << 16)
            if not step:
                return None
            piece = inflate.decompress(step)
            pos += len(step)
            out.append(piece)
            got += len(piece)
            if not checked and (got >= 8 or inflate.eof):
                start = b"".join(out)
                if not start.startswith(b"WARC/"):
                    return None
                checked = True
            if not whole and checked:
                start = b"".join(out)
                if b"\r\n\r\n" in start:
                    return start, None
    except zlib.error:
        return None
    return b"".join(out), pos - len(inflate.unused_data)


def parse_record(data: bytes):
    """Header fields (lower-case names) and block, or None where the record is not complete."""
    head, sep, rest = data.partition(b"\r\n\r\n")
    if not sep or not head.startswith(b"WARC/"):
        return None
    fields = {}
    for line in head.decode("utf-8", "replace").split("\r\n")[1:]:
        k, _, v = line.partition(":")
        fields[k.strip().lower()] = v.strip()
    try:
        n = int(fields["content-length"])
    except (KeyError, ValueError):
        return None
    return (fields, rest[:n]) if len(rest) >= n else None


def records_in(handle, size: int, start: int, stop: int, mark: int | None = None):
    """``(offset, fields, block)`` of the records whose first byte lies in [start, stop). ``mark``
    is where some member begins that is the first one of the range, or lies before it."""
    window, at = _Window(handle, size, start), start
    if mark is not None:
        if mark >= stop:
            return
        # members from the mark on are stepped over; scanning starts where the first own one does
        at = mark
        window = _Window(handle, size, at)
        while at < start:
            got = _member(window, at, True)
            if got is None:
                break
            at = got[1]
            window.drop(at)
        at = max(at, start)
    chained = False
    while at < stop and at < size:
        if not chained:
            seen = window.need(at, FETCH)
            hit = seen.find(MAGIC)
            if hit < 0:
                at += max(1, len(seen) - len(MAGIC) + 1)
                window.drop(at)
                continue
            at += hit
            if at >= stop:
                return
        got = _member(window, at, True)
        record = parse_record(got[0]) if got else None
        if record is None:
            if chained:
                chained = False  # padding or foreign bytes: search on
                continue
            at += 1
            continue
        if not chained and mark is None and at > 0 and not _carries_on(handle, size, got[1], stop):
            at += 1  # bytes of a payload
            continue
        yield at, *record
        at, chained = got[1], True
        window.drop(at)
        if window.need(at, 3) != MAGIC:
            chained = False


def _carries_on(handle, size: int, at: int, stop: int) -> bool:
    """Whether records follow each other from ``at`` to the end of the range or of the file."""
    window = _Window(handle, size, at)
    while at < stop and at < size:
        got = _member(window, at, True) if window.need(at, 3) == MAGIC else None
        if got is None or parse_record(got[0]) is None:
            return False
        at = got[1]
        window.drop(at)
    return at >= size or _member(window, at, False) is not None


def _read(folder: str, with_payload: bool):
    names = ["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "payload"]

    def emit(rows):
        cols = list(zip(*rows)) if rows else [[]] * 7
        kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds)], names=names)

    def run(batches):
        filesystem, root = _open_fs(folder)
        for b in batches:
            for name, size, start, stop, mark in zip(*(b.column(c).to_pylist() for c in ("file", "size", "start", "stop", "mark"))):
                rows, held = [], 0
                with filesystem.open_input_file(f"{root}/{name}") as handle:
                    for _, f, block in records_in(handle, size, start, stop, mark):
                        revisit = f.get("warc-type") == "revisit"
                        if not revisit and f.get("warc-type") != "response":
                            continue
                        length = int(f.get("x-payload-length", len(block))) if revisit else len(block)
                        digest = f.get("warc-payload-digest", "").partition(":")[2] if revisit else digest_of(block)
                        refers = _page(f.get("warc-refers-to")) if revisit else None
                        rows.append((_page(f.get("warc-record-id")), f.get("warc-target-uri"), f["warc-type"], refers, length, digest, block if with_payload and not revisit else None))
                        held += len(block) if with_payload else 64
                        if held > 4 << 20:
                            yield emit(rows)
                            rows, held = [], 0
                if rows:
                    yield emit(rows)

    return run


def read_archives(spark: SparkSession, folder: str, manifest: DataFrame, span: int = RANGE, with_payload: bool = True) -> DataFrame:
    """All records of the manifest's files, read by byte ranges of ``span``. Files without marks
    (a null, or no such column) are read by scanning alone."""
    marks = F.col("marks") if "marks" in manifest.columns else F.lit(None).cast("array<long>")
    ranges = manifest.select("file", "size", marks.alias("marks"), F.explode(F.expr(f"sequence(0L, greatest(size - 1, 0L), {span}L)")).alias("start"))
    ranges = ranges.select("file", "size", "start", F.least(F.col("start") + span, "size").alias("stop"), F.expr(f"get(marks, cast(start div {MARK} as int))").alias("mark"))
    spans = manifest.agg(F.sum(F.ceil(F.col("size") / span))).first()[0]
    ranges = ranges.repartition(min(max(1, int(spans or 1)), RANGES), F.xxhash64("file", "start"))
    return ranges.mapInArrow(_read(folder, with_payload), RECORD)


def round_trip(pages: DataFrame, folder: str | None = None, span: int = RANGE, with_payload: bool = False) -> DataFrame:
    spark = pages.sparkSession
    folder = folder or shared_path(spark, "warc")
    return read_archives(spark, folder, write_archives(pages, folder), span, with_payload)
