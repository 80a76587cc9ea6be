import hashlib
import io
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from veilframe.llm import media as M


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 9), st.integers(1, 9), st.booleans(), st.integers(0, 2**32 - 1))
def test_containers_round_trip(h, w, colour, seed):
    image = np.random.default_rng(seed).integers(0, 256, (h, w, 3) if colour else (h, w)).astype(np.uint8)
    assert (M.decode(M.encode_ppm(image) if colour else M.encode_pgm(image)) == image).all()
    assert (M.decode(M.encode_bmp(image)) == image).all()


def test_other_netpbm_kinds():
    assert M.decode(b"P1\n# c\n2 2\n1 0\n01").tolist() == [[0, 255], [255, 0]]
    assert M.decode(b"P2 3 1 9 # x\n1 2 9").tolist() == [[1, 2, 9]]
    assert M.decode(b"P3 1 1 255 7 8 9").tolist() == [[[7, 8, 9]]]
    assert M.decode(b"P4 9 1\n\x80\x80").tolist() == [[0, *[255] * 7, 0]]
    assert M.decode(b"P5 1 1 65535\n\x01\x02").tolist() == [[258]]


@pytest.mark.parametrize("data", [b"", b"P5", b"P9 1 1", b"P5 2 2 255\n\x00", b"BM" + b"\0" * 60, b"P2 2 2 255 1", b"nothing"])
def test_bad_images(data):
    with pytest.raises(M.MediaError):
        M.decode(data)


def test_area_resize_by_brute_force():
    image = np.random.default_rng(1).integers(0, 256, (7, 5)).astype(float)
    for h, w in ((3, 2), (7, 5), (1, 1), (10, 9)):
        got = M.area_resize(image, h, w)
        fine = np.repeat(np.repeat(image, h, axis=0), w, axis=1)  # every cell is whole pixels now
        want = fine.reshape(h, 7, w, 5).mean(axis=(1, 3))
        assert np.allclose(got, want)


def test_difference_hash():
    ramp = np.tile(np.arange(64), (16, 1)).astype(np.uint8)
    assert M.difference_hash(ramp) == (1 << 64) - 1 and M.difference_hash(ramp[:, ::-1]) == 0


def test_tiles(spark):
    image = np.arange(48).reshape(6, 8).astype(np.uint8)
    df = spark.createDataFrame([(1, M.encode_pgm(image), "c"), (2, None, "c"), (3, b"bad", "c"), (4, b"", "c")], "id long, media binary, tile string")
    got = {r.id: r for r in M.media_tiles(df, side=4).collect()}
    assert np.load(io.BytesIO(got[1].tile)).shape == (4, 4) and (got[1].height, got[1].width, got[1].channels) == (6, 8, 1)
    assert got[2].tile is None and got[3].error and got[4].dhash is None


@pytest.mark.parametrize("container", ["pgm", "bmp"])
def test_texts_come_back(spark, container):
    texts = [None, "", "a", "é" * 40, "x" * 64, "y" * 65, "z" * 5000]
    df = spark.createDataFrame([(i, t, "f") for i, t in enumerate(texts)], "doc_id long, text string, feature string")
    rows = {r.doc_id: r for r in M.text_media(df, container).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        n = max(64, -(-len(raw) // 64) * 64)
        pay = raw.ljust(n, b"\0")
        r = rows[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), n, hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-64:]))
        stored = M.store(pay, container)
        assert (r.media_bytes, r.media_sha256) == (len(stored), hashlib.sha256(stored).hexdigest())
    assert rows[0][1:] == rows[1][1:]
    assert M.text_media(df.where("doc_id > 99")).count() == 0
