import hashlib

import numpy as np
import pytest

from entlink.llm import warc_chain as w
from entlink.llm.sharedfiles import publishing
from entlink.storage import scratch_path

FAKE = "WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 5\r\n\r\nhello\r\n\r\n"


def pages(spark):
    rows = [(i, f"http://x/{i}", f"page {i} " + "lorem " * (i * 13 % 400)) for i in range(120)]
    rows += [(200, "u", FAKE * 3 + "tail"), (201, None, None), (202, "u", ""), (203, "ü\r\nX: y", "é" * 60), (204, "u", "é" * 60)]
    rows += [(50 + 300, "u", rows[50][2] * 3), (7 + 400, "u", "same " * 40), (408, "u", "same " * 40), (409, "u", "same " * 40), (408, "u", "same " * 40)]
    rows += [(None, "u", "same " * 40), (500, "u", FAKE + "x" * 5000 + FAKE)]
    return spark.createDataFrame([(*r, "z") for r in rows], "page_id long, url string, html string, size string"), rows


def test_round_trip_with_magic_inside_payloads(spark):
    df, rows = pages(spark)
    for file_bytes, range_bytes in ((1 << 30, 700), (4000, 1500), (1 << 20, 1 << 20)):
        files = w.write_warc(df.repartition(2), file_bytes=file_bytes)
        got = w.read_warc(files, range_bytes).collect()
        assert len(got) == len(rows)
        key = lambda i, n: (i is None, i or 0, n)
        want = []
        for i, _, h in rows:
            raw = (h or "").encode()
            same = [j for j, _, t in rows if (t or "") == (h or "") and j is not None]
            again = len(raw) >= 100 and (i is None or min(same) < i)
            want.append((i, len(raw), hashlib.sha256(raw).hexdigest(), "revisit" if again else "response", min(same) if again else None))
        assert sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got), key=lambda x: key(x[0], x[2])) == sorted(
            want, key=lambda x: key(x[0], x[2])
        )
        assert all(r.payload == (dict((i, h or "") for i, _, h in rows)[r.page_id]).encode() for r in got if r.record_type == "response" and r.page_id is not None)


def test_empty_and_broken(spark):
    df, _ = pages(spark)
    assert w.read_warc(w.write_warc(df.where("false"))).count() == 0
    uri = scratch_path(spark, "broken") + "/a.warc"
    one = w._record(1, "u", b"x" * 50, hashlib.sha256(b"x" * 50).hexdigest(), None, False)
    with publishing(uri) as out:
        out.write(one + b"garbage" + one)
    files = spark.createDataFrame([(uri, 2 * len(one) + 7)], "uri string, size long")
    with pytest.raises(Exception, match="no record begins"):
        w.read_warc(files).count()


def test_range_exits_by_plain_walk():
    rng = np.random.default_rng(3)
    off = np.unique(rng.integers(0, 1000, 200))
    nxt = off + rng.integers(1, 60, len(off))
    by = dict(zip(off.tolist(), nxt.tolist()))
    for o, e in zip(off.tolist(), w.range_exits(off, nxt, 1000).tolist()):
        at = by[o]
        while at < 1000 and at in by:
            at = by[at]
        assert e == (at if at >= 1000 else -1)


def test_scan_time_is_linear_in_hostile_payloads(tmp_path):
    import time

    took = {}
    for n in (20_000, 80_000):
        body = w.VERSION * n + b"a: b\r\n" * n + b"WARC/1.1\r\nContent-Length: 5\r\n\r\nhello\r\n\r\n"
        path = tmp_path / f"{n}.warc"
        path.write_bytes(b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: %d\r\n\r\n" % len(body) + body + b"\r\n\r\n")
        size, at = path.stat().st_size, time.perf_counter()
        with open(path, "rb") as f:
            found = w.scan_range(f, size, 0, size)
        took[n] = time.perf_counter() - at
        assert [found[0][1], len(found)] == [size, 2]
    assert took[80_000] < 12 * took[20_000] + 0.2


def test_headers_across_range_ends(tmp_path):
    records = [b"WARC/1.1\r\nX-Long: %s\r\n folded: line\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (b"v" * k, k % 7, b"p" * (k % 7)) for k in (3, 40_000, 17, 70_000, 5)]
    path = tmp_path / "a.warc"
    path.write_bytes(b"".join(records))
    size, starts = path.stat().st_size, [sum(map(len, records[:i])) for i in range(len(records))]
    for step in (50, 1000, 30_000):
        with open(path, "rb") as f:
            got = [x for at in range(0, size, step) for x in w.scan_range(f, size, at, min(size, at + step))]
        assert [x[0] for x in got] == starts and [x[1] for x in got] == starts[1:] + [size]
