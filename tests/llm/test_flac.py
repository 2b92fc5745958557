import random

import numpy as np
import pytest

from zplane.llm import flac_codec as fc
from zplane.llm.media import decode_flac, encode_flac, pcm_blocks, text_media


def _payloads():
    rng = random.Random(5)
    outlier = bytearray(b"\x80" * 4096)
    outlier[100], outlier[4095] = 0, 255
    return [b"", b"x", bytes(64), bytes(range(256)), rng.randbytes(10_000), b"ab" * 5000, b"hello world " * 700, bytes([0, 255] * 3000), bytes(outlier), b"word " * 10 + bytes(14)]


@pytest.mark.parametrize("order", [0, 1, 4, 8])
def test_round_trip_with_and_without_seek_table(order):
    data = _payloads()
    streams = fc.encode(data, order)
    for p, s, g in zip(data, streams, fc.decode(streams)):
        assert "error" not in g and (g["samples"] + 128).astype(np.uint8).tobytes() == p
        if p:
            bare = bytearray(s[:42])
            bare[4] |= 0x80
            again = fc.decode([bytes(bare) + s[fc._metadata(s)["at"] :]])[0]
            assert (again["samples"] + 128).astype(np.uint8).tobytes() == p


def test_random_short_payloads():
    rng = random.Random(9)
    data = [bytes(rng.choice((0, 0, 0, 97, 98, 200)) for _ in range(rng.randint(1, 300))) for _ in range(300)]
    assert [(g["samples"] + 128).astype(np.uint8).tobytes() for g in fc.decode(fc.encode(data))] == data


def test_damage_is_found_and_named():
    s = fc.encode([b"hello world " * 400])[0]
    for at in range(len(s) - 200, len(s), 7):
        bad = bytearray(s)
        bad[at] ^= 16
        assert "error" in fc.decode([bytes(bad)])[0]
    good = fc.encode([b"fine" * 40])[0]
    got = fc.decode([bytes(bad), good, None, b"", s[:-100]])
    assert [("error" in g) for g in got] == [True, False, True, True, True]


def test_columns(spark):
    df = spark.createDataFrame([(1, b"abc" * 4000), (2, None), (1, b"abc" * 4000)], "doc_id long, data binary")
    out = decode_flac(encode_flac(df, "data", ("doc_id",)), "media", ("doc_id",))
    rows = sorted(out.collect(), key=lambda r: (r.doc_id, r.n_samples))
    assert [r.pcm for r in rows] == [b"abc" * 4000] * 2 + [b""]
    blocks = pcm_blocks(out.where("doc_id = 1").limit(1)).orderBy("first_sample").collect()
    assert b"".join(b.pcm for b in blocks) == b"abc" * 4000 and [b.first_sample for b in blocks] == [0, 4096, 8192]
    broken = spark.createDataFrame([(b"nonsense",), (None,)], "media binary")
    assert all(r.pcm is None and r.error for r in decode_flac(broken).collect())


def test_text_media_edges(spark):
    import hashlib
    import zlib

    rows = [(1, None), (2, ""), (3, "a" * 64), (4, "é" * 40000), (None, "x"), (3, "a" * 64)]
    got = text_media(spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as media", "2 as pcm")).collect()
    assert len(got) == len(rows)
    for r in got:
        raw = {1: b"", 2: b"", 3: b"a" * 64, 4: "é".encode() * 40000, None: b"x"}[r.doc_id]
        pad = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(pad), hashlib.sha256(pad).hexdigest(), zlib.crc32(pad[-64:]))
    assert text_media(spark.createDataFrame([], "doc_id long, text string")).count() == 0
