import hashlib
import random
import zlib

from harvestgrid.llm import mpegts as ts


def test_round_trip_sizes():
    rng = random.Random(1)
    sizes = [*range(0, 800), 16383, 16384, 16385, 16384 * 4, 16384 * 4 + 1, 200_000]
    for n in sizes:
        data = rng.randbytes(n)
        payload = ts.pad(data)
        assert len(payload) % 64 == 0 and payload[:n] == data and not any(payload[n:])
        for unit in (64, 170, 16384) if n < 800 else (16384,):
            media = ts.mux(payload, unit)
            back = ts.demux(media)
            assert len(media) % 188 == 0 and back.payload == payload
            assert back.counter_errors == back.table_errors == 0
            assert [u[0] for u in back.units] == [3600 * k for k in range(len(back.units))]
            assert [k for k, u in enumerate(back.units) if u[3]] == list(range(0, len(back.units), 4))


def test_known_checksum_and_damage():
    assert ts.section_crc(b"123456789") == 0x0376E6E7
    media = bytearray(ts.mux(b"x" * 64 * 300))
    lost = bytes(media[: 188 * 5] + media[188 * 6 :])
    assert ts.demux(lost).counter_errors == 1
    media[188 * 0 + 15] ^= 1
    assert ts.demux(bytes(media)).table_errors >= 1
    assert ts.demux(b"").payload is None and ts.demux(None).payload is None and ts.demux(b"abc").payload is None


def test_rows(spark):
    rows = [(1, None, "a"), (2, "", "b"), (3, "é" * 50_000, "c"), (4, "same", "d"), (4, "same", "e"), (None, "x", "f")]
    got = ts.stored_and_read(spark.createDataFrame(rows, "doc_id long, text string, media string")).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    for i, t, _ in rows:
        r, p = by[i][0], ts.pad((t or "").encode())
        assert (r.n_bytes, r.payload_bytes) == (len((t or "").encode()), len(p))
        assert r.payload_sha256 == hashlib.sha256(p).hexdigest() and r.tail_crc32 == zlib.crc32(p[-64:])
    assert by[1][0].media_sha256 == by[2][0].media_sha256 and by[4][0].asDict() == by[4][1].asDict()
    assert ts.stored_and_read(spark.createDataFrame([], "doc_id long, text string")).count() == 0
