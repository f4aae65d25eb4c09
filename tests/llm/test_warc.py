import gzip

import pyarrow as pa
from helpers import duck, rows

from navspark.llm import warc as W

PAGES = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("html", pa.string())])
COLS = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
BIG = "<p>ä" * 600


def sample():
    return [(1, "http://a/ b\r\n", BIG), (2, None, BIG), (9, "http://x", BIG), (3, "u", "short"), (4, "u", "short"), (5, "u", None), (6, "u", ""), (7, "u", "WARC/1.1\r\n\r\n" * 200), (8, "u", "\x00" * 1000)]


def test_equals_sql(spark):
    df = spark.createDataFrame(sample(), "page_id long, url string, html string").withColumnRenamed("url", "url").repartition(3)
    got = rows(W.op1_result(spark, df), [*COLS, "gap"])
    sql = W.OP1_SQL
    assert got == sorted((tuple(r) for r in duck(f"select {', '.join(COLS)}, gap from ({sql})", pages=(sample(), PAGES))), key=str)


def test_null_ids_repeats_and_empty(spark):
    df = spark.createDataFrame([(None, "u", BIG), (4, "u", BIG), (4, "u", BIG)], "page_id long, url string, html string")
    got = rows(W.op1_result(spark, df), COLS)
    assert sorted((r[0] or 0, r[3], r[4]) for r in got) == sorted([(0, "revisit", 4), (4, "response", None), (4, "response", None)], key=str)
    assert W.op1_result(spark, df.limit(0)).count() == 0


def _archive():
    recs = [W.record("response", i, f"http://h/{i}", f"payload {i} ".encode() * 50, W.hashlib.sha1(f"payload {i} ".encode() * 50).hexdigest()) for i in range(6)]
    return recs, b"".join(map(W.member, recs)), b"".join(recs)


def ids(data):
    return [x["id"][12:-1] if isinstance(x, dict) else "gap" for _, _, x in W.salvage(data)]


def test_members_form_a_plain_gzip_file():
    recs, packed, plain = _archive()
    assert gzip.decompress(packed) == plain
    assert ids(packed) == ids(plain) == ids(gzip.compress(plain)) == list("012345")


def test_salvage_members():
    recs, packed, _ = _archive()
    parts = [W.member(r) for r in recs]
    at = sum(map(len, parts[:2]))
    bad = bytearray(packed)
    for k in range(at + 20, at + 60):
        bad[k] ^= 0x5A
    got = list(W.salvage(bytes(bad)))
    assert ids(bytes(bad)) == ["0", "1", "gap", "3", "4", "5"]
    assert [(s, e) for s, e, x in got if isinstance(x, str)] == [(at, at + len(parts[2]))]
    assert ids(packed[: -len(parts[5]) // 2]) == ["0", "1", "2", "3", "4", "gap"]
    assert ids(b"junk" + packed) == ["gap", *"012345"]
    assert ids(packed[: at + 30] + packed[at + len(parts[2]) :]) == ["0", "1", "gap", "3", "4", "5"]


def test_salvage_plain_records():
    recs, _, plain = _archive()
    at = len(recs[0])
    bad = plain.replace(b"payload 1 p", b"paxload 1 p", 1)
    got = list(W.salvage(bad))
    assert ids(bad) == ["0", "gap", "2", "3", "4", "5"]
    assert [(s, e, x) for s, e, x in got if isinstance(x, str)] == [(at, at + len(recs[1]), "block digest")]
    assert ids(plain.replace(b"Content-Length", b"Content-Lxngth", 2)) == ["gap", "1", "2", "3", "4", "5"]
    assert ids(b"") == []


def test_payload_round_trip(spark):
    df = spark.createDataFrame(sample(), "page_id long, url string, html string")
    path = W.scratch(spark, "t")
    W.write_warc(df.coalesce(1), path, max_bytes=200)
    assert spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).count() > 3
    got = {r.record_id: bytes(r.payload).decode() for r in W.read_warc(spark, path).collect() if r.record_type == "response"}
    want = {f"<urn:x-page:{p}>": h or "" for p, _, h in sample() if p not in (1, 2)}
    assert got == want
