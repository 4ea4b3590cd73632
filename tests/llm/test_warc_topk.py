import gzip
import hashlib
import io
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecpath.llm import topk, warc


def archive(n=20):
    members = [warc.page_record(i, f"http://x/{i}", f"<p>page {i}</p>".encode() * 40, "d", None, False) for i in range(n)]
    starts = np.cumsum([0] + [len(m) for m in members]).tolist()
    return b"".join(members), starts


def read(body):
    reader = warc.Salvage(io.BytesIO(body), len(body))
    found = [r.fields["warc-record-id"] for r in reader.records()]
    return found, reader.gaps


def ids(*numbers):
    return [f"<urn:page:{i}>" for i in numbers]


def test_sound_archive():
    body, _ = archive()
    assert read(body) == (ids(*range(20)), [])
    assert read(b"") == ([], [])


def test_damaged_member_is_passed_over_and_logged():
    body, starts = archive()
    broken = bytearray(body)
    broken[starts[5] + 60] ^= 0xFF
    found, gaps = read(bytes(broken))
    assert found == ids(*[i for i in range(20) if i != 5])
    assert [(g[0], g[1]) for g in gaps] == [(starts[5], starts[6])]


def test_missing_start_junk_and_truncation():
    body, starts = archive()
    found, gaps = read(body[: starts[3]] + b"\x1f\x8b\x08junk" * 9 + body[starts[3] : starts[10] - 7])
    assert found == ids(*range(9))
    assert len(gaps) == 2 and gaps[1][0] == starts[9] + 63
    found, gaps = read(body[10:])
    assert found == ids(*range(1, 20)) and gaps[0][0] == 0


def test_uncompressed_archive_and_bad_lengths():
    import gzip

    parts = [gzip.decompress(warc.page_record(i, "u", b"x" * 200, "d", None, False)) for i in range(4)]
    assert read(b"".join(parts))[0] == ids(0, 1, 2, 3)
    bad = parts[1].replace(b"Content-Length: ", b"Content-Length: 9")
    found, gaps = read(parts[0] + bad + parts[2] + parts[3])
    assert found == ids(0, 2, 3) and len(gaps) == 1


def test_salvage_within_members_of_several_records():
    plain = [gzip.decompress(warc.page_record(i, f"u{i}", random.Random(i).randbytes(3000), "d", None, False)) for i in range(5)]
    bad = [plain[0], plain[1].replace(b"Content-Length: ", b"Content-Length: 9"), plain[2], plain[3][:-9] + b"?????" + plain[3][-4:], plain[4]]
    found, gaps = read(gzip.compress(b"".join(bad)))
    assert found == ids(0, 2, 4) and len(gaps) == 2
    whole = gzip.compress(b"".join(plain))
    found, gaps = read(whole[: len(whole) * 7 // 10])
    assert found == ids(0, 1, 2) and len(gaps) == 1 and "truncated" in gaps[0][2]
    hurt = bytearray(whole)
    hurt[len(whole) * 7 // 10] ^= 255
    found, gaps = read(bytes(hurt))
    assert found == ids(0, 1, 2, 4) and len(gaps) == 1


def test_long_headers_of_records_that_are_not_compressed():
    plain = [gzip.decompress(warc.page_record(i, "data:" + "x" * 200_000, b"<p>", "d", None, False)) for i in range(2)]
    assert read(b"".join(plain)) == (ids(0, 1), [])
    assert read(plain[0] + b"WARC/1.1\r\nA: " + b"x" * 200_000)[0] == ids(0)


def test_pages_round_trip(spark):
    big = "<p>" + "long text " * 300000 + "</p>"
    rows = [(i, f"http://x/{i}\r\nEvil: 1", f"<p>{i % 7}</p>" * 30) for i in range(40)]
    rows += [(100, None, None), (101, "u", ""), (102, "u", "é" * 49), (103, "u", "é" * 49), (104, "u", "é" * 50), (105, "u", "é" * 50), (106, "u", big), (107, "u", big)]
    folder = warc.new_folder(spark, "warc")
    written = warc.write_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), folder)
    records = warc.read_archives(written, folder)
    got = {r.page_id: r for r in warc.page_records(records).collect()}
    assert len(got) == len(rows)
    first = {}
    for i, _, h in sorted(rows):
        b = (h or "").encode()
        f = first.setdefault(b, i)
        r = got[i]
        revisit = len(b) >= 100 and f != i
        assert (r.payload_bytes, r.payload_digest) == (len(b), hashlib.sha256(b).hexdigest())
        assert (r.record_type, r.refers_to) == (("revisit", f) if revisit else ("response", None))
    assert records.where("kind = 'gap'").count() == 0
    assert warc.page_records(records, strict=True).count() == len(rows)
    lost = records.limit(3).withColumns({"kind": F.lit("gap"), "gap_end": F.lit(9).cast("long"), "gap_reason": F.lit("torn")})
    with pytest.raises(Exception, match="to 9 of .*torn"):
        warc.page_records(lost, strict=True).collect()
    assert warc.page_records(warc.read_archives(spark.createDataFrame([("none.warc.gz",)], "path string"), folder)).count() == 0
    empty = warc.write_pages(spark.createDataFrame([], "page_id long, url string, html string"), warc.new_folder(spark, "warc"))
    assert empty.count() == 0


def brute(rows, every=50, k=5):
    q = {}
    for i, v in rows:
        if i is None or not v or any(x is None or not np.isfinite(x) for x in v):
            continue
        q.setdefault(i, []).append([int(np.floor(256 * float(x))) for x in v])
    out = []
    for i in q:
        if i % every == 0:
            s = sorted((-sum(a * b for a, b in zip(q[i][0], v)), j) for j in q if j != i for v in q[j] if len(v) == len(q[i][0]))
            out += [(i, r + 1, j, -t) for r, (t, j) in enumerate(s[:k])]
    return sorted(out)


@pytest.mark.parametrize("block", [64, 7, 1000])
def test_topk_matches_brute_force(spark, block):
    rng = random.Random(block)
    rows = [(i, [float(np.float32(rng.gauss(0, 1))) for _ in range(6)]) for i in range(150)]
    rows += [(200 + i, [0.5, -0.5, 0.25, 0.0, 1.0, -1.0]) for i in range(20)]
    rows += [(300, None), (350, [None] * 6), (400, [float("nan")] * 6), (450, [float("inf")] * 6), (None, [1.0] * 6), (500, []), (550, [1.0, 2.0]), (600, [3.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = sorted(tuple(r) for r in topk.topk_inner(df, rows_per_block=block).collect())
    assert got == brute(rows)


def test_topk_of_few_and_no_rows(spark):
    schema = "vec_id long, embedding array<float>"
    rows = [(0, [1.0, 2.0]), (1, [1.0, 1.0])]
    assert sorted(tuple(r) for r in topk.topk_inner(spark.createDataFrame(rows, schema)).collect()) == [(0, 1, 1, 256 * 256 * 3)]
    assert topk.topk_inner(spark.createDataFrame([], schema)).count() == 0


def test_topk_of_large_components(spark):
    schema = "vec_id long, embedding array<double>, score string, rank int"
    rows = [(0, [1.0, 2.0]), (1, [600000.0, 1.0]), (2, [3.0, 1.0]), (3, [2.0**25, -1.0]), (50, [-(2.0**20), 0.5])]
    got = sorted(tuple(r) for r in topk.topk_inner(spark.createDataFrame([(*r, "x", 1) for r in rows], schema)).collect())
    assert got == brute(rows)
    # beyond a long: ranked by what they are, given as the nearest long
    rows = [(0, [1e30, 1.0]), (1, [1e30, 0.0]), (2, [-1e300, 0.0]), (3, [1e3, 0.0]), (4, [2e30, 0.0])]
    got = [(r.vec_id, r.score) for r in topk.topk_inner(spark.createDataFrame([(*r, "x", 1) for r in rows], schema)).orderBy("rank").collect()]
    top, low = (1 << 63) - 1, -(1 << 63)
    assert {v: s for v, s in got} == {1: top, 3: top, 4: top, 2: low} and got[-1][0] == 2


def test_topk_of_empty_vectors(spark):
    rows = [(0, []), (1, []), (2, [1.0])]
    assert [tuple(r) for r in topk.topk_inner(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()] == [(0, 1, 1, 0)]
