import base64
import hashlib
import io

import pytest

from rarecount.llm import op7_warc as W

SCHEMA = "page_id long, url string, html string"


def pages():
    out = [(i, f"http://h/{i}", f"<p>{i} " + "text " * (i % 50)) for i in range(200)]
    return out + [(300, "http://h/x", "<p>7 " + "text " * 7), (301, None, None), (302, "u\r\nx", ""), (None, "n", "only here"), (303, "é", "ü\r\n\r\n" * 9), (1, "http://h/1", "<p>1 text "), (304, "long", "y" * 300_000)]


def test_round_trip(spark):
    df = spark.createDataFrame(pages(), SCHEMA).selectExpr("*", "'z' as payload", "1 as k").repartition(3)
    got = sorted((tuple(r) for r in W.round_trip(spark, df).collect()), key=str)
    first = {}
    for p, _, h in pages():
        h = h or ""
        first[h] = min((x for x in (first.get(h), p) if x is not None), default=None)
    want = []
    for p, _, h in pages():
        raw = (h or "").encode()
        again = p != first[h or ""]
        want.append((p, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "revisit" if again else "response", first[h or ""] if again else None))
    assert got == sorted(want, key=str)
    assert W.round_trip(spark, spark.createDataFrame([], SCHEMA)).count() == 0


def archive(n=40):
    out = io.BytesIO()
    W.put_archive(out, iter([W.record(i, f"http://a/{i}", b"hello world %d " % i * 20, None, False) for i in range(n)]), 1 << 30)
    return out.getvalue()


def test_leading_dictionary_and_one_frame_a_record():
    raw = archive()
    assert raw[:4] == (0x184D2A5D).to_bytes(4, "little")
    assert [W.summary(r)[0] for r in W.read_archive(io.BytesIO(raw))] == list(range(40))


def test_damage_is_found():
    raw = archive(3)
    for bad in (raw[:-5], b"\0" + raw[1:], raw[:6]):
        with pytest.raises((W.Malformed, W.zstandard.ZstdError)):
            list(map(W.summary, W.read_archive(io.BytesIO(bad))))
    one = W.record(1, "u", b"abc", None, False)
    for bad in (one[:-1], one.replace(b"Content-Length: 8", b"Content-Length: 9"), one.replace(b"abc", b"abd"), one.replace(b"WARC/1.1", b"XARC/1.1")):
        with pytest.raises(W.Malformed):
            W.summary(bad)
