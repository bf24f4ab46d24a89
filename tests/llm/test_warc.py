import hashlib

from helpers import same_rows

from nudgegraph.llm import warc
from nudgegraph.session import scratch_path

PAGES = [(1, "http://a/1", "x" * 1500), (2, None, "x" * 1500), (3, "http://a/3\r\nEvil: 1", "short"), (4, "http://a/4", None), (5, "u", "short"), (None, "n", "x" * 1500), (7, "u", "WARC/1.1\r\n\r\nnot a record \x1f\x8b\x08" + "é" * 900)]


def test_sql_twin(spark, sf, duck):
    same_rows(warc.warc_round_trip(spark.read.parquet(f"{sf}/pages.parquet")), duck.sql(warc.ORACLE))


def test_odd_rows(spark):
    df = spark.createDataFrame(PAGES, "page_id long, url string, html string")
    out = {r.page_id: r for r in warc.warc_round_trip(df).collect()}
    assert len(out) == len(PAGES)
    assert out[2].record_type == "response" and out[1].record_type == "revisit" and out[1].refers_to == 2 and out[None].refers_to == 2
    assert out[4].payload_bytes == 0 and out[5].record_type == out[3].record_type == "response"
    assert out[7].payload_digest == hashlib.sha1(PAGES[6][2].encode()).hexdigest()
    assert warc.warc_round_trip(df.limit(0)).count() == 0


def _archive(n=12):
    members = [warc.gzip_member(warc._record("response", i, f"http://h/{i}", (f"payload {i} " * 50).encode(), hashlib.sha1((f"payload {i} " * 50).encode()).hexdigest(), None)) for i in range(n)]
    return members, b"".join(members)


def _ids(data):
    return [int(h["x-page-id"]) for _, _, h, _ in warc.salvage(data) if h is not None], [(a, b) for a, b, h, _ in warc.salvage(data) if h is None]


def test_salvage_finds_later_members():
    members, data = _archive()
    assert _ids(data) == (list(range(12)), [])
    at = sum(map(len, members[:4]))
    broken = bytearray(data)
    broken[at + 30] ^= 0xFF
    ids, gaps = _ids(bytes(broken))
    assert ids == [i for i in range(12) if i != 4] and gaps == [(at, at + len(members[4]))]
    ids, gaps = _ids(data[: at - 7])
    assert ids == [0, 1, 2] and gaps == [(at - len(members[3]), at - 7)]
    ids, gaps = _ids(b"junk before" + data)
    assert ids == list(range(12)) and gaps == [(0, 11)]
    assert _ids(b"") == ([], []) and _ids(b"nothing here") == ([], [(0, 12)])


def test_salvage_bare_records():
    bare = [warc._record("response", i, None, b"p" * 100, hashlib.sha1(b"p" * 100).hexdigest(), None) for i in range(3)]
    wrong = bare[1].replace(b"pppp", b"pppq", 1)
    ids, gaps = _ids(bare[0] + wrong + bare[2])
    assert ids == [0, 2] and gaps == [(len(bare[0]), len(bare[0]) + len(wrong))]


def test_gaps_are_reported(spark, tmp_path):
    members, data = _archive()
    broken = bytearray(data)
    broken[len(members[0]) + 20] ^= 0xFF
    (tmp_path / "a.warc.gz").write_bytes(bytes(broken))
    out = warc.read_archives(spark.createDataFrame([(f"file://{tmp_path}/a.warc.gz",)], "path string"))
    assert out.where("gap").count() == 1 and out.where("not gap").count() == 11


def test_archives_roll(spark):
    df = spark.createDataFrame([(i, "u", "body %d " % i * 400) for i in range(40)], "page_id long, url string, html string").coalesce(1)
    manifest = warc.write_archives(df, scratch_path(spark, "roll"), roll_bytes=2000)
    assert manifest.count() > 1


def test_long_url(spark):
    rows = [(1, "http://a/" + "x" * (2 << 20), "one"), (2, "http://a/" + " " * (1 << 19), "two"), (3, "http://a/3", "three")]
    out = warc.warc_round_trip(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert sorted((r.page_id, r.payload_bytes, r.record_type) for r in out) == [(1, 3, "response"), (2, 3, "response"), (3, 5, "response")]
