import base64
import hashlib
import io

import pyarrow as pa
import zstandard

from harvestgrid.llm import warc


def test_bundle_random_access():
    out = io.BytesIO()
    out.close, keep = (lambda: None), out
    w = warc.BundleWriter(out, frame_bytes=1000)
    records = [warc.build_record(k, f"http://x/{k}", b"p" * (k * 37 % 3000)) for k in range(200)]
    places = [w.add(r) for r in records]
    w.close()
    data = keep.getvalue()
    reader = warc.BundleReader(pa.BufferReader(data))
    for r, (frame, at) in list(zip(records, places))[::-1]:
        assert reader.frame(frame)[at : at + len(r)] == r
    assert len(reader.frames) > 50
    plain = b"".join(zstandard.ZstdDecompressor().stream_reader(io.BytesIO(data), read_across_frames=True).readall() for _ in range(1))
    assert plain == b"".join(records)


def test_rows(spark):
    rows = [
        (1, "u1", "<p>a"), (2, "u2", "<p>a"), (0, "u0", "<p>a"), (3, None, None), (4, "u4", ""), (5, "u\r\n5", "é" * 300_000),
        (None, "n", "<p>a"), (None, "n", "only"), (None, "n", "only"), (6, "x", "twice"), (6, "x", "twice"),
    ]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("sha", df_lit("clash")).repartition(3)
    for least in (0, 4):
        folder, index = warc.write(df, min_bytes=least, frame_bytes=64, bundle_bytes=100)
        got = sorted(map(tuple, warc.read(folder, index).collect()), key=str)
        groups = {}
        for i, _, h in rows:
            groups.setdefault(h or "", []).append(i)
        want = []
        for i, u, h in rows:
            p = (h or "").encode()
            ids = [x for x in groups[h or ""] if x is not None]
            again = len(p) >= least and ids and i != min(ids)
            digest = base64.b32encode(hashlib.sha1(p).digest()).decode()
            u = u.replace("\r", "%0D").replace("\n", "%0A") if u else u
            want.append((i, u, len(p), digest, "revisit" if again else "response", min(ids) if again else None))
        assert got == sorted(want, key=str)
    folder, index = warc.write(df.limit(0))
    assert warc.read(folder, index).count() == 0


def df_lit(x):
    from pyspark.sql import functions as F

    return F.lit(x)
