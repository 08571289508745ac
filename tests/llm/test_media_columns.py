import hashlib
import zlib

import numpy as np
import pytest

from spanfocus.llm import media_columns as M
from tests.llm.fixtures import edge_docs, no_docs


@pytest.mark.parametrize("kind", [None, M.NONE, M.SUB, M.UP])
def test_round_trip(kind):
    rng = np.random.default_rng(1)
    for shape in ((1, 64), (3, 64), (70, 64), (33, 7)):
        image = rng.integers(0, 256, shape, dtype=np.uint8)
        assert (M.decode_png(M.encode_png(image, kind)) == image).all()


def filtered_by_hand(image, kinds):
    """Every PNG filter written byte by byte."""
    h, w = image.shape
    out = np.zeros((h, w + 1), np.uint8)
    for y in range(h):
        out[y, 0] = kinds[y]
        for x in range(w):
            a = int(image[y, x - 1]) if x else 0
            b = int(image[y - 1, x]) if y else 0
            c = int(image[y - 1, x - 1]) if x and y else 0
            p = a + b - c
            near = a if abs(p - a) <= abs(p - b) and abs(p - a) <= abs(p - c) else b if abs(p - b) <= abs(p - c) else c
            out[y, x + 1] = (int(image[y, x]) - (0, a, b, (a + b) // 2, near)[kinds[y]]) % 256
    return out


def test_all_filters_mixed():
    rng = np.random.default_rng(2)
    image = rng.integers(0, 256, (40, 9), dtype=np.uint8)
    kinds = rng.integers(0, 5, 40)
    assert (M._unfilter(filtered_by_hand(image, kinds)) == image).all()


def test_damage_is_found():
    data = bytearray(M.encode_png(np.zeros((2, 64), np.uint8)))
    for at in (0, 20, 45, len(data) - 2):
        broken = data.copy()
        broken[at] ^= 1
        with pytest.raises(ValueError):
            M.decode_png(bytes(broken))
    with pytest.raises(ValueError):
        M.decode_png(bytes(data[:-12]))


def test_hash_follows_low_frequencies():
    y = np.linspace(0, 200, 64)[:, None] + np.zeros((64, 64))
    near = np.clip(y + np.random.default_rng(3).integers(-3, 4, y.shape), 0, 255)
    far = y[::-1]
    bits = [np.unpackbits(np.frombuffer(M.cosine_hash(v.astype(np.uint8)), np.uint8)) for v in (y, near, far)]
    assert (bits[0] != bits[2]).sum() > 0
    assert len(bits[0]) == 64


def test_documents(spark):
    docs = edge_docs(spark)
    made = M.store_and_read_png(docs).collect()
    apart = M.read_png(M.store_png(docs)).collect()
    key = lambda r: (r.doc_id is None, r.doc_id or 0, r.n_bytes)
    assert sorted(made, key=key) == sorted(apart, key=key)
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert len(made) == docs.count()
    for r in made:
        data = (texts[r.doc_id] or "").encode()
        payload = M.padded(data)
        assert (r.n_bytes, r.payload_bytes) == (len(data), len(payload))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.tail_crc32 == zlib.crc32(payload[-64:])
    assert len({r.media_sha256 for r in made if r.doc_id in (3, 4)}) == 1
    assert M.store_and_read_png(no_docs(spark)).count() == 0
