import hashlib
import zlib

import numpy as np
import pytest

from tests.llm.conftest import ROWS
from tracegroup.llm import media as m


def test_round_trip(odd_docs, no_docs):
    for form in ("ppm", "bmp"):
        rows = m.with_media(odd_docs, form=form)
        got = {(str(r["doc_id"]), r["payload"]): r for r in rows.collect()}
        for d in m.digests(rows).collect():
            r = next(r for r in got.values() if hashlib.sha256(r["payload"]).hexdigest() == d["payload_sha256"])
            assert d["tail_crc32"] == zlib.crc32(r["payload"][-16:]) and d["media_sha256"] == hashlib.sha256(r["media"]).hexdigest()
        for i, t, *_ in ROWS:
            body = (t or "").encode()
            want = body + b" " * ((-len(body)) % 192 if body else 192)
            assert got[str(i), want]["n_bytes"] == len(body)
    assert m.with_media(no_docs).count() == 0


def test_decoders():
    rng = np.random.default_rng(1)
    rgb, grey = rng.integers(0, 256, (7, 5, 3)).astype(np.uint8), rng.integers(0, 256, (4, 9)).astype(np.uint8)
    assert (m.decode(m.encode_ppm(rgb)) == rgb).all() and (m.decode(m.encode_ppm(grey)) == grey).all()
    assert (m.decode(m.encode_bmp(rgb)) == rgb).all()
    assert (m.decode(b"P2 # c\n3 1\n# d\n255\n1 2 3\n") == [[1, 2, 3]]).all()
    assert (m.decode(b"P3 1 1 255 9 8 7") == [[[9, 8, 7]]]).all()
    assert (m.decode(b"P1 2 2 1 0\n01") == [[0, 255], [255, 0]]).all()
    assert (m.decode(b"P4 2 1\n\x80") == [[0, 255]]).all()
    for bad in (b"", b"P", b"P9 1 1", b"GIF89a", b"P2 2 2 255 1"):
        with pytest.raises(ValueError):
            m.decode(bad)


def test_area_resize():
    g = np.arange(24.0).reshape(4, 6)
    assert np.allclose(m.area_resize(g, 2, 3), g.reshape(2, 2, 3, 2).mean((1, 3)))
    assert np.allclose(m.area_resize(g, 3, 5).mean(), g.mean())
    assert np.allclose(m.area_resize(np.full((3, 64), 7.0), 8, 9), 7)


def test_tiles_are_npy(tmp_path):
    t = m.tile_of(np.full((3, 64, 3), 200, np.uint8))
    (tmp_path / "a.npy").write_bytes(m.npy(t))
    assert (np.load(tmp_path / "a.npy") == 200).all() and t.shape == (16, 16, 3)
