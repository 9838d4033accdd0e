import glob
import gzip
import hashlib
import os
import random

from evensort.llm import warc


def pages():
    rng = random.Random(1)
    rows = [(i, f"http://x/{i}", rng.choice(["", "short", "é" * 60, "<p>" + "b" * rng.randint(97, 5000)])) for i in range(120)]
    return rows + [(200, None, None), (None, "u", "é" * 60), (3, "u\r\nWARC/1.1", "é" * 60), (300, "v", "WARC/1.1\r\n\r\n" * 30), (301, "v", os.urandom(10).hex() * 100_000)]


def expected(rows):
    first = {}
    for i, _, t in rows:
        if t is not None and len(t.encode()) >= 100 and i is not None:
            first[t] = min(i, first.get(t, i))
    out = []
    for i, _, t in rows:
        raw = (t or "").encode()
        to = first.get(t) if len(raw) >= 100 and first.get(t) != i else None
        out.append((str(i), len(raw), hashlib.sha256(raw).hexdigest(), "response" if to is None else "revisit", None if to is None else str(to)))
    return sorted(out, key=str)


def test_round_trip(spark):
    rows = pages()
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    path = warc.new_folder(spark)
    warc.write(df, path, records_per_file=17)
    found = warc.read(spark, path, payload=True)
    assert found.where("kind = 'gap'").count() == 0
    got = [(r.page_id if r.page_id != "null" else "None", r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in found.collect()]
    assert sorted(got, key=str) == expected(rows)
    files = glob.glob(path.removeprefix("file://") + "/part-*")
    whole = b"".join(gzip.decompress(open(f, "rb").read()) for f in files)
    assert whole.count(b"WARC-Record-ID: ") == len(rows)


def test_shuffled_way_gives_the_same(spark, monkeypatch):
    monkeypatch.setattr(warc, "BROADCAST_ROWS", 0)
    rows = pages()
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").drop("url")
    got = [(str(r.page_id), len(r.payload), r.digest, "revisit" if r.revisit else "response", str(r["first"]) if r.revisit else None) for r in warc.decide(df).collect()]
    assert sorted(got, key=str) == expected(rows)
    empty = warc.new_folder(spark)
    warc.write(df.limit(0), empty)
    assert warc.read(spark, empty).count() == 0


def records(n):
    made = []
    for i in range(n):
        body = f"page {i} ".encode() * 40
        made.append(warc.record(i, b"http://x", body, hashlib.sha256(body).hexdigest(), None))
    return made


def test_salvage_of_damaged_members():
    members = [warc.member(r) for r in records(6)]
    starts = [sum(map(len, members[:i])) for i in range(7)]
    data = bytearray(b"".join(members))
    data[starts[1] + 30] ^= 0xFF
    data[starts[4] : starts[4] + 3] = b"???"
    out = list(warc.salvage(bytes(data)))
    ids = [o[3][0]["warc-record-id"] for o in out if o[0] == "record"]
    assert ids == [f"<urn:page:{i}>".encode() for i in (0, 2, 3, 5)]
    assert [(o[1], o[2]) for o in out if o[0] == "gap"] == [(starts[1], starts[2]), (starts[4], starts[5])]
    cut = list(warc.salvage(bytes(data[: starts[6] - 5])))
    # a damaged member and the cut-off one behind it are one gap
    assert cut[-1][0] == "gap" and cut[-1][1:3] == (starts[4], starts[6] - 5)


def test_salvage_of_plain_records():
    made = records(4)
    made[1] = made[1].replace(b"page 1 ", b"page ! ", 1)
    made[2] = made[2].replace(b"Content-Length: 3", b"Content-Length: 9")
    data = b"junk" + b"".join(made)
    out = list(warc.salvage(data))
    assert [o[3][0]["warc-record-id"] for o in out if o[0] == "record"] == [b"<urn:page:0>", b"<urn:page:3>"]
    assert [o[3] for o in out if o[0] == "gap"] == ["no member or version line", "payload digest is wrong"]
    assert sum(o[2] - o[1] for o in out) == len(data)


def test_large_member_ends_with_zero():
    data = bytes(1 << 24) + b"x"
    made = warc.member(data)
    assert made[-1] == 0 and gzip.decompress(made) == data
    assert warc.inflate(made, 0)[0] == data


def test_good_records_around_a_bad_one_in_a_member():
    made = records(5)
    bad = made[1].replace(b"page 1 ", b"page ! ", 1)
    data = warc.member(made[0] + bad + made[2]) + warc.member(made[3])
    out = list(warc.salvage(data))
    assert [o[3][0]["warc-record-id"] for o in out if o[0] == "record"] == [b"<urn:page:0>", b"<urn:page:2>", b"<urn:page:3>"]
    gaps = [o for o in out if o[0] == "gap"]
    assert len(gaps) == 1 and gaps[0][3] == f"payload digest is wrong (bytes {len(made[0])} to {len(made[0]) + len(bad)} of the member)"
    assert gaps[0][1:3] == (0, len(warc.member(made[0] + bad + made[2])))


def test_a_cut_member_gives_its_first_records():
    rng = random.Random(5)
    made = []
    for i in range(40):
        body = rng.randbytes(3000)
        made.append(warc.record(i, None, body, hashlib.sha256(body).hexdigest(), None))
    whole = gzip.compress(b"".join(made))
    for cut in (len(whole) - 6, len(whole) // 2, 20):
        out = list(warc.salvage(whole[:cut]))
        found = [o[3][0]["warc-record-id"] for o in out if o[0] == "record"]
        assert found == [f"<urn:page:{i}>".encode() for i in range(len(found))]
        assert len(found) >= 40 * cut // len(whole) - 2 and out[-1] == ("gap", 0, cut, "member is damaged")
    broken = bytearray(whole)
    broken[len(whole) // 2] ^= 0xFF
    found = [o for o in warc.salvage(bytes(broken) + warc.member(made[0])) if o[0] == "record"]
    assert len(found) >= 19 and found[-1][3][0]["warc-record-id"] == b"<urn:page:0>"


def test_gaps_come_back_from_damaged_files(spark):
    df = spark.createDataFrame([(i, "u", f"page {i} " * 60) for i in range(12)], "page_id bigint, url string, html string").coalesce(1)
    path = warc.new_folder(spark)
    warc.write(df, path)
    file = glob.glob(path.removeprefix("file://") + "/part-*")[0]
    data = bytearray(open(file, "rb").read())
    data[len(data) // 2] ^= 0xFF
    os.remove(file)
    for crc in glob.glob(os.path.dirname(file) + "/.*.crc"):
        os.remove(crc)
    with open(file, "wb") as f:
        f.write(data)
    found = warc.read(spark, path).collect()
    assert sum(r.kind == "record" for r in found) == 11 and [r.reason for r in found if r.kind == "gap"] == ["member is damaged"]


def test_empty_and_clashing_tables(spark):
    df = spark.createDataFrame([(1, "u", "<p>", "d", 1, "x")], "page_id bigint, url string, html string, digest string, first int, payload string")
    path = warc.new_folder(spark)
    warc.write(df, path)
    assert [r.payload_bytes for r in warc.read(spark, path).collect()] == [3]


def test_large_pages_make_small_files(spark, monkeypatch):
    monkeypatch.setattr(warc, "FILE_BYTES", 5000)
    df = spark.createDataFrame([(i, "u", f"{i} " * 400) for i in range(20)], "page_id bigint, url string, html string").coalesce(1)
    path = warc.new_folder(spark)
    warc.write(df, path)
    assert len(glob.glob(path.removeprefix("file://") + "/part-*")) >= 4
    assert warc.read(spark, path).count() == 20
