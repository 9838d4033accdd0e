import hashlib
import random
import zlib

from evensort.llm import ogg


def slow_crc(data):
    c = 0
    for b in data:
        c ^= b << 24
        for _ in range(8):
            c = (c << 1 ^ 0x04C11DB7 if c >> 31 else c << 1) & 0xFFFFFFFF
    return c


def test_checksum_equals_bitwise_form():
    rng = random.Random(1)
    for n in (0, 1, 2, 27, 300):
        data = rng.randbytes(n)
        assert ogg.crc(data) == slow_crc(data)


def test_round_trip_of_any_length():
    rng = random.Random(2)
    for n in (0, 1, 63, 64, 255, 256, 4079, 4080, 4081, 61_200, 61_201, 200_003):
        raw = rng.randbytes(n)
        payload = raw + bytes(-n % 64 or (0 if n else 64))
        made = ogg.write(payload, n)
        back, size, end, file = ogg.decode(made)
        assert (back, size) == (payload, n) and end == len(payload) / ogg.RATE
        assert set(file.streams) == {ogg.SAMPLES, ogg.FACTS} and not file.damaged and not file.missing
        assert all(s.ended for s in file.streams.values())


def test_packets_of_any_size_survive_paging():
    rng = random.Random(3)
    packets = [(rng.randbytes(n), i + 1) for i, n in enumerate((0, 255, 510, 70_000, 3, 65_025, 200_000, 254))]
    data = b"".join(ogg.StreamWriter(7).pages(packets, begin=True, end=True))
    stream = ogg.read(data).streams[7]
    assert stream.packets == [p for p, _ in packets] and stream.granules[-1] == 8
    assert stream.ended


def test_damage_is_listed_and_the_rest_read():
    payload = bytes(range(256)) * 1000
    made = bytearray(ogg.write(payload, len(payload)))
    third = made.index(b"OggS", 70_000)
    made[third + 100] ^= 1
    file = ogg.read(bytes(made))
    assert len(file.damaged) == 1 and file.missing == 1
    assert 0 < len(b"".join(file.streams[ogg.SAMPLES].packets[1:])) < len(payload)
    assert file.streams[ogg.FACTS].packets[1] == b"n_bytes=256000"


def test_query_columns(spark):
    texts = [None, "", "é" * 70, "x" * 200_000, "same", "same"]
    df = spark.createDataFrame([(i, t, b"z") for i, t in enumerate(texts)], "doc_id int, text string, Media binary")
    rows = {r.doc_id: r for r in ogg.describe(ogg.encode(df)).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        payload = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        r = rows[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest())
        assert r.tail_crc32 == zlib.crc32(payload[-64:]) and r.damaged_pages == 0
    assert rows[4][3:] == rows[5][3:]
    assert ogg.describe(ogg.encode(df.limit(0))).count() == 0


def test_damage_anywhere_never_raises(spark):
    rng = random.Random(4)
    payload = rng.randbytes(64 * 2000)
    made = ogg.write(payload, 100)
    files = [b"", b"OggS", made[:40], rng.randbytes(500), None]
    for at in [*range(0, 160, 7), *(rng.randrange(len(made)) for _ in range(20))]:
        broken = bytearray(made)
        broken[at] ^= 1 << rng.randrange(8)
        files.append(bytes(broken))
    for f in files:
        if f is not None:
            samples, n, end, file = ogg.decode(f)
            assert n in (100, None) and len(samples) <= len(payload)
    df = spark.createDataFrame([(i, f) for i, f in enumerate(files)], "doc_id int, media binary")
    rows = {r.doc_id: r for r in ogg.describe(df).collect()}
    assert rows[4].media_bytes is None and all(rows[i].media_bytes == len(f) for i, f in enumerate(files) if f is not None)
    # the first page lost: its header goes, the samples stay
    head = bytearray(made)
    head[10] ^= 1
    samples, n, end, file = ogg.decode(bytes(head))
    assert samples == payload and n == 100 and file.damaged
