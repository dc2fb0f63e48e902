import gzip
import os

from carepath.llm import warc


def test_records_of_any_size():
    spec, big = warc.ArchiveSpec(), os.urandom(17 << 20)
    rows = [(1, "http://a/é b", b"x" * 200, None), (2, None, b"", None), (None, "u", b"\r\n\r\n\x00", None), (3, "u", b"x" * 200, 1), (4, "u", big, None)]
    content = b"".join(warc.record(*r, spec) for r in rows)
    assert all(warc.record(*r, spec)[-1] == 0 for r in rows)
    assert gzip.decompress(content).count(b"WARC/1.1\r\n") == 5
    got = list(warc.records(content))
    assert [p for _, p in got] == [b"x" * 200, b"", b"\r\n\r\n\x00", b"", big]
    assert got[3][0]["WARC-Type"] == "revisit" and got[3][0]["WARC-Refers-To"] == got[0][0]["WARC-Record-ID"]


def test_round_trip_is_deterministic(spark, tmp_path):
    rows = [(i, f"http://x/{i}", ("same text " * 30) if i % 3 == 0 else f"page {i} " * 40) for i in range(200)] + [(200, None, None), (None, "u", "same text " * 30), (7, "again", "small"), (8, "v", "small"), (201, "w", "ü" * 100_000)]
    df = spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, shard int")
    spec = warc.ArchiveSpec(shard_bytes=20_000, roll_bytes=3_000, bins=64)
    made = []
    for n, parts in ((1, 2), (2, 5)):
        warc.write(df.repartition(parts), str(tmp_path / str(n)), spec)
        made.append({f: (tmp_path / str(n) / "data" / f).read_bytes() for f in os.listdir(tmp_path / str(n) / "data") if f.endswith(".gz")})
    assert made[0] == made[1] and len(made[0]) > 5
    back = warc.read(spark, str(tmp_path / "1")).collect()
    assert sorted((r.page_id or -1, r.payload_bytes) for r in back) == sorted((r[0] or -1, len((r[2] or "").encode())) for r in rows)
    assert {r.refers_to for r in back if r.record_type == "revisit"} == {0}
    assert sum(r.record_type == "revisit" for r in back) == 67
    assert warc.exists(spark, str(tmp_path / "1"))


def test_empty_table(spark, tmp_path):
    warc.write(spark.createDataFrame([], "page_id long, url string, html string"), str(tmp_path / "e"))
    assert warc.read(spark, str(tmp_path / "e")).count() == 0


def test_shards_hold_what_they_may(spark, tmp_path):
    """One far id, one id and one missing id with many pages: no shard but of one payload exceeds its bytes; files are in order of id."""
    rows = [(i, "u", f"page {i} " * 30) for i in range(400)] + [(10**15, "far", "x" * 50)] + [(7, "u", f"again {i} " * 30) for i in range(300)] + [(None, "u", f"none {i} " * 30) for i in range(300)] + [(-(1 << 63), "first", "y"), ((1 << 63) - 1, "last", "z")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    spec = warc.ArchiveSpec(shard_bytes=50_000, roll_bytes=4_000)
    made = []
    for n, parts in ((1, 1), (2, 6)):
        folder = tmp_path / str(n)
        warc.write(df.repartition(parts), str(folder), spec)
        made.append({f: (folder / "data" / f).read_bytes() for f in sorted(os.listdir(folder / "data")) if f.endswith(".gz")})
    assert made[0] == made[1]
    sizes, seen = {}, []
    for name, content in made[0].items():
        for fields, payload in warc.records(content):
            sizes[name.split("-")[1]] = sizes.get(name.split("-")[1], 0) + len(payload) + 512
            seen.append(int(fields.get("Page-Id", warc.NO_ID)))
    assert max(sizes.values()) <= spec.shard_bytes and len(sizes) > 10
    assert seen == sorted(seen) and len(seen) == len(rows)
    assert warc.read(spark, str(tmp_path / "1")).count() == len(rows)
