"""WARC archives: deduplicated writing, and reading by boundary-chain verification.

Writing.  Equal payloads of ``MIN_DUPLICATE`` bytes or more are stored once, by
the least page id; the others become revisit records that name it.  Payload
digests are compared as narrow rows, so page bodies move only if a body must
meet a long list of revisits.

Reading.  Files are cut into byte ranges that tasks scan on their own.  A task
reports each place that looks like a record start with the offset at which
that record would end; a payload may well contain such a place.  The true
records are the ones that the chain of record ends reaches from offset zero.
Within a range a candidate's first successor beyond the range is found by
pointer jumping over arrays; between ranges it is done by joins that double
the jump each round, so a file of R ranges takes about log2 R rounds.  Then
each range follows its own chain from its entry point.

Defined results: null html counts as empty; of repeated page ids each row gives
a record; a null page id sorts after all others; a file whose chain breaks
before its end raises ``ValueError``; empty tables give no files and no rows.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.llm.sharedfiles import publishing, reading
from entlink.storage import discard, materialize, scratch_path

MIN_DUPLICATE = 100
FILE_BYTES = 64 << 20
RANGE_BYTES = 8 << 20
VERSION = b"WARC/1.1\r\n"
_LENGTH = re.compile(rb"(?mi)^content-length:[ \t]*(\d+)[ \t]*\r$")
# The version line and the fields after it; anything else, such as another version line, ends the match.
_FIELDS = re.compile(rb"WARC/1\.1\r\n(?:[^\x00-\x20\x7f:]+:[^\r\n]*\r\n(?:[ \t][^\r\n]*\r\n)*+)*+")
HEAD_BYTES = 1 << 14


def _record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, revisit: bool) -> bytes:
    body = b"" if revisit else payload
    head = [
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: <urn:page:{page_id}>",
        f"WARC-Target-URI: {(url or '').encode('ascii', 'backslashreplace').decode().translate({13: None, 10: None})}",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"X-Page-Id: {'' if page_id is None else page_id}",
        f"X-Payload-Length: {len(payload)}",
        "Content-Type: text/html",
    ]
    if revisit:
        head.append(f"WARC-Refers-To: <urn:page:{refers_to}>")
    head.append(f"Content-Length: {len(body)}")
    return VERSION + "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def revisits(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """``(page_id, digest, refers_to)`` of pages whose payload a page with a lesser id has."""
    html = F.coalesce(F.col(html_col), F.lit(""))
    slim = pages.where(F.octet_length(html) >= MIN_DUPLICATE).select(F.col(id_col).cast("long").alias("page_id"), F.unhex(F.sha2(html, 256)).alias("digest"))
    slim = materialize(slim, "warc-digests")
    shared = slim.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1")
    again = slim.join(shared.select("digest", "refers_to"), "digest").where("page_id > refers_to or page_id is null")
    return materialize(again.select("page_id", "digest", "refers_to").distinct(), "warc-revisits")


def write_warc(pages: DataFrame, path: str | None = None, id_col: str = "page_id", url_col: str | None = "url", html_col: str = "html",
               file_bytes: int = FILE_BYTES) -> DataFrame:
    """Write all pages; returns ``(uri, size)`` of the files."""
    spark = pages.sparkSession
    path = path or scratch_path(spark, "warc")
    html = F.coalesce(F.col(html_col), F.lit(""))
    url = F.col(url_col) if url_col and url_col in pages.columns else F.lit(None).cast("string")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), url.alias("url"), html.alias("html"))
    again = revisits(pages, id_col, html_col).select(F.col("page_id").alias("again"), F.col("digest").alias("again_digest"), "refers_to")
    # The reread table has a known size: Spark broadcasts it only below its threshold.
    plan = rows.join(again, F.col("page_id").eqNullSafe(F.col("again")) & (F.unhex(F.sha2("html", 256)) == F.col("again_digest")), "left")

    def run(batches):
        part, seq, stream, out, at = TaskContext.get().partitionId(), 0, None, None, 0
        for b in batches:
            for page_id, url, text, refers_to in zip(*(b.column(i).to_pylist() for i in range(4))):
                payload = text.encode("utf-8")
                if stream is None:
                    uri = f"{path}/{part:06d}-{seq:06d}.warc"
                    stream, at, seq = publishing(uri), 0, seq + 1
                    out = stream.__enter__()
                raw = _record(page_id, url, payload, hashlib.sha256(payload).hexdigest(), refers_to, refers_to is not None)
                out.write(raw)
                at += len(raw)
                if at >= file_bytes:
                    stream.__exit__(None, None, None)
                    stream = None
                    yield pa.RecordBatch.from_arrays([pa.array([uri]), pa.array([at])], ["uri", "size"])
        if stream is not None:
            stream.__exit__(None, None, None)
            yield pa.RecordBatch.from_arrays([pa.array([uri]), pa.array([at])], ["uri", "size"])

    return materialize(plan.select("page_id", "url", "html", "refers_to").mapInArrow(run, "uri string, size long"), "warc-files")


class _Window:
    """A file read in large pieces, with access to any span."""

    def __init__(self, file, size: int, start: int, stop: int):
        self.file, self.size, self.start = file, size, start
        file.seek(start)
        self.data = file.read(min(stop, size) - start)

    def span(self, at: int, n: int) -> bytes:
        n = min(n, self.size - at)
        if self.start <= at and at + n <= self.start + len(self.data):
            return self.data[at - self.start : at - self.start + n]
        self.file.seek(at)
        return self.file.read(max(0, n))


def scan_range(file, size: int, start: int, stop: int) -> list[tuple]:
    """Candidates that begin in ``[start, stop)``: offset, successor, header length and content length.

    Fields are read from a version line up to the first line that is none, and a version line is none, so no byte is
    read for two candidates and the time is linear in the range, whatever a payload holds.
    """
    win = _Window(file, size, start, stop + len(VERSION) - 1)
    found, at = [], win.data.find(VERSION)
    while at >= 0:
        off = start + at
        fields = _FIELDS.match(win.data, at)
        if win.data.find(b"\n", fields.end()) < 0:  # the last line of the range may go on beyond it
            head = _header_across(win, off, size)
        else:
            head = win.data[at : fields.end() + 2] if win.data.startswith(b"\r\n", fields.end()) else b""
        length = _LENGTH.search(head)
        if length:
            end = off + len(head) + int(length[1]) + 4
            if end <= size and win.span(end - 4, 4) == b"\r\n\r\n":
                found.append((off, end, len(head), int(length[1])))
        at = win.data.find(VERSION, fields.end())
    return found


def _header_across(win: _Window, off: int, size: int) -> bytes:
    """The header at ``off`` with its blank line, read on as far as its fields go; empty if there is none."""
    reach = 2 * HEAD_BYTES
    while True:
        raw = win.span(off, reach)
        end = _FIELDS.match(raw).end()
        if raw.startswith(b"\r\n", end):
            return raw[: end + 2]
        # A line that is cut by the end of what was read may still be a field.
        if off + len(raw) >= size or b"\n" in raw[end:]:
            return b""
        reach *= 2


def range_exits(offsets: np.ndarray, nexts: np.ndarray, stop: int) -> np.ndarray:
    """Per candidate, where its chain first lands at or beyond ``stop``, or -1 if it breaks before."""
    jump = nexts.copy()
    while True:
        at = np.searchsorted(offsets, jump)
        hit = (at < len(offsets)) & (jump < stop) & (jump >= 0)
        hit[hit] = offsets[at[hit]] == jump[hit]
        moved = jump.copy()
        moved[hit] = jump[at[hit]]
        moved[(jump < stop) & (jump >= 0) & ~hit] = -1
        if np.array_equal(moved, jump):
            return jump
        jump = moved


CANDIDATE = "uri string, size long, start long, offset long, next long, head long, length long, exit long"


def candidates(files: DataFrame, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """Every apparent record of every range, with its successor and its exit from the range."""
    starts = F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("size") - 1, F.lit(0)), F.lit(range_bytes).cast("long")))
    ranges = files.where("size > 0").select("uri", "size", starts.alias("start"))
    parts = int(files.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        for b in batches:
            for uri, size, start in zip(*(b.column(i).to_pylist() for i in range(3))):
                with reading(uri) as f:
                    got = scan_range(f, size, start, min(size, start + range_bytes))
                if got:
                    off, nxt, head, length = (np.array(c, np.int64) for c in zip(*got))
                    exits = range_exits(off, nxt, min(size, start + range_bytes))
                    n = len(off)
                    cols = [pa.array([uri] * n), pa.array([size] * n), pa.array([start] * n), off, nxt, head, length, exits]
                    yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in cols], [c.split()[0] for c in CANDIDATE.split(", ")])

    return materialize(ranges.repartition(parts, "uri", "start").mapInArrow(run, CANDIDATE), "warc-candidates")


def range_entries(found: DataFrame) -> DataFrame:
    """``(uri, offset)`` of the first true record of each range, reached from offset zero by doubling jumps."""
    jumps = found.select("uri", "offset", F.col("exit").alias("jump"))
    reached = found.where("offset = 0").select("uri", "offset")
    longest = found.agg(F.max("size")).first()[0] or 0
    old = []
    while True:
        ahead = reached.join(jumps, ["uri", "offset"]).select("uri", F.col("jump").alias("offset"))
        grown = materialize(reached.unionByName(ahead.join(jumps.select("uri", "offset"), ["uri", "offset"], "left_semi")).distinct(), "warc-reached")
        n, m = grown.count(), reached.count()
        old.append(reached)
        reached = grown
        if n == m or not longest:
            break
        far = jumps.select("uri", F.col("offset").alias("jump"), F.col("jump").alias("then"))
        doubled = jumps.join(far, ["uri", "jump"], "left").select("uri", "offset", F.coalesce("then", "jump").alias("jump"))
        old.append(jumps)
        jumps = materialize(doubled, "warc-jumps")
    for df in old:
        discard(df)
    return reached


RECORD = "uri string, offset long, page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"


def read_warc(files: DataFrame, range_bytes: int = RANGE_BYTES, with_payload: bool = True) -> DataFrame:
    """True records of the files, in the columns of ``RECORD``.

    A response's length and digest are taken from its stored payload, and must
    agree with its header; a revisit's from its header.
    """
    found = candidates(files, range_bytes)
    reached = range_entries(found)
    whole = found.join(reached, ["uri", "offset"], "left_semi").where("exit = size").select("uri")
    cut = files.where("size > 0").join(whole, "uri", "left_anti").head(1)
    if cut:
        raise ValueError(f"{cut[0].uri}: no record begins where the one before it ends")
    entries = reached.select("uri", F.col("offset").alias("entry"))
    rows = found.select(F.struct("uri", "start").alias("range"), "uri", "size", "start", "offset", "next", "head", "length")
    chain = F.sort_array(F.collect_list(F.struct("offset", "next", "head", "length")))
    # One range's candidates: bounded by its bytes.
    ranges = rows.groupBy("uri", "start", "size").agg(chain.alias("chain"))
    first = entries.withColumn("start", F.col("entry") - F.pmod("entry", F.lit(range_bytes)))
    first = first.groupBy("uri", "start").agg(F.min("entry").alias("entry"))
    todo = ranges.join(first, ["uri", "start"]).select("uri", "size", "entry", "chain")
    names = [c.split()[0] for c in RECORD.split(", ")]
    kinds = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary()]

    def run(batches):
        for b in batches:
            for uri, size, entry, steps in zip(*(b.column(i).to_pylist() for i in range(4))):
                by, at, out, held = {s["offset"]: s for s in steps}, entry, [], 0
                lo, hi = entry, max(s["next"] for s in steps)
                with reading(uri) as f:
                    win = _Window(f, size, lo, hi)
                    while at in by:
                        s = by[at]
                        raw = win.span(at, s["head"] + s["length"])
                        out.append(_parse(uri, at, raw[: s["head"]], raw[s["head"] :], with_payload))
                        held += len(raw)
                        at = s["next"]
                        if held > 8 << 20:
                            yield pack(out)
                            out, held = [], 0
                if out:
                    yield pack(out)

    def pack(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    return todo.mapInArrow(run, RECORD)


def _parse(uri: str, offset: int, head: bytes, body: bytes, with_payload: bool) -> tuple:
    fields = dict(line.split(": ", 1) for line in head.decode("utf-8").split("\r\n")[1:] if ": " in line)
    kind = fields["WARC-Type"]
    page, refers = fields.get("X-Page-Id", ""), fields.get("WARC-Refers-To", "")
    digest, size = fields["WARC-Payload-Digest"].removeprefix("sha256:"), int(fields["X-Payload-Length"])
    if kind == "response":
        if len(body) != size or hashlib.sha256(body).hexdigest() != digest:
            raise ValueError(f"{uri}: the payload at {offset} does not have the digest of its header")
    target = int(refers.removeprefix("<urn:page:").removesuffix(">")) if kind == "revisit" else None
    return (uri, offset, int(page) if page else None, fields.get("WARC-Target-URI"), kind, size, digest, target, body if with_payload and kind == "response" else None)
