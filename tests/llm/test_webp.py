import random

import numpy as np
import pytest

from polyedge.llm import webp


def picture(h, w, colours, seed):
    rng = np.random.default_rng(seed)
    table = rng.integers(0, 2**32, colours, dtype=np.uint64).astype(np.uint32)
    smooth = (np.add.outer(np.arange(h), np.arange(w)) // 3) % colours
    return table[np.where(rng.random((h, w)) < 0.7, smooth, rng.integers(0, colours, (h, w)))]


@pytest.mark.parametrize("cache_bits", [0, 1, 6, 11])
@pytest.mark.parametrize("references", [False, True])
@pytest.mark.parametrize("colours", [1, 2, 3, 14, 200])
def test_codes_cache_and_references(cache_bits, references, colours):
    x = picture(13, 21, colours, colours)
    assert (webp.decode_image(webp.encode_image(x, (), cache_bits, references)) == x).all()


@pytest.mark.parametrize("mode", range(14))
def test_predictor_modes(mode):
    x = picture(9, 11, 90, mode)
    modes = np.full((3, 3), mode)
    assert (webp.decode_image(webp.encode_image(x, [("predictor", 2, modes)], 4, True)) == x).all()


@pytest.mark.parametrize("colours", [1, 2, 4, 5, 16, 17, 256])
def test_palette(colours):
    x = picture(17, 19, colours, 5)
    assert (webp.decode_image(webp.encode_image(x, [("palette",)])) == x).all()


def test_stacked_transforms():
    rng = np.random.default_rng(3)
    x = picture(16, 24, 120, 9)
    elements = rng.integers(0, 2**32, (4, 6), dtype=np.uint64).astype(np.uint32)
    modes = rng.integers(0, 14, (4, 6))
    steps = [("predictor", 2, modes), ("cross", 2, elements), ("green",)]
    assert (webp.decode_image(webp.encode_image(x, steps, 5, True)) == x).all()


def test_near_distances_are_distinct_and_sorted():
    assert len(set(webp.NEAR)) == 120
    d = [x * x + y * y for x, y in webp.NEAR]
    assert d == sorted(d)


def test_values_and_prefixes():
    for v in [1, 2, 3, 4, 5, 6, 7, 8, 9, 100, 121, 4096, 70000]:
        s, n, extra = webp._prefix(v)
        r = webp.BitReader(extra.to_bytes(8, "little"))
        assert webp.read_value(r, s) == v and r.at == n


@pytest.mark.parametrize("size", [0, 1, 575, 576, 577, 40_000])
def test_payload_round_trip(size):
    rng = random.Random(size)
    raw = bytes(rng.choices(range(256) if size % 2 else b"etaoin shrdlu", k=size))
    padded = webp.pad(raw)
    assert len(padded) % 576 == 0 and len(padded) >= 576
    media = webp.store_bytes(padded)
    assert webp.read_bytes(media) == padded
    assert webp.store_bytes(padded) == media


def test_long_payload_continues_in_further_files(monkeypatch):
    monkeypatch.setattr(webp, "MOST_ROWS", 3)
    payload = bytes(range(256)) * 9 * 4
    payload = payload[: len(payload) // 576 * 576]
    assert webp.read_bytes(webp.store_bytes(payload)) == payload
    assert webp.store_bytes(payload).count(b"WEBPVP8L") > 1


def symbol_by_symbol(monkeypatch):
    """Make the reader take every picture symbol by symbol."""
    kept = webp.read_group

    def slow(r, codes, width, n):
        out = []
        while len(out) < n:
            s = codes[0].symbol(r)
            if s < 256:
                red, blue = codes[1].symbol(r), codes[2].symbol(r)
                out.append(codes[3].symbol(r) << 24 | red << 16 | s << 8 | blue)
                continue
            count = webp.read_value(r, s - 256)
            d = webp.read_value(r, codes[4].symbol(r))
            d = d - 120 if d > 120 else max(1, webp.NEAR[d - 1][0] + webp.NEAR[d - 1][1] * width)
            for _ in range(count):
                out.append(out[-d])
        return np.array(out[:n], np.uint32)

    monkeypatch.setattr(webp, "_read_parallel", slow)
    assert kept is webp.read_group


@pytest.mark.parametrize("payload", [b"the same pixels by either way" * 50, bytes(range(256)) * 20, b"ab" * 2000, b"x" * 5000, bytes(random.Random(1).choices(b"etaoin shrdlu.\n", k=9000))])
def test_all_positions_at_once_equal_symbol_by_symbol(monkeypatch, payload):
    media = webp.store_bytes(webp.pad(payload))
    x = picture(13, 21, 60, 4)
    other = webp.encode_image(x, (), 0, True)
    fast, fast_other = webp.decode_image(media), webp.decode_image(other)
    symbol_by_symbol(monkeypatch)
    assert (webp.decode_image(media) == fast).all() and (webp.decode_image(other) == fast_other).all()


def test_writer_uses_transforms_codes_and_references(monkeypatch):
    seen = {"references": 0, "codes": 0}
    kept = webp._copies

    def copies(x):
        out = kept(x)
        seen["references"] += len(out)
        at = 0
        for a, n, d in out:
            assert a >= at and webp.LEAST_COPY <= n <= webp.MOST_COPY and 0 < d <= a
            assert all(x[a + i] == x[a + i - d] for i in range(n))
            at = a + n
        return out

    monkeypatch.setattr(webp, "_copies", copies)
    rng = random.Random(2)
    words = ["".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(2, 9))) for _ in range(200)]
    text = webp.pad(" ".join(rng.choices(words, k=2000)).encode())
    media = webp.store_bytes(text)
    assert webp.read_bytes(media) == text and len(media) < 0.5 * len(text) and seen["references"] > 100
    few = webp.pad(b"0101101" * 400)
    assert len(webp.store_bytes(few)) < 200 and webp.read_bytes(webp.store_bytes(few)) == few


def test_code_lengths_stay_within_fifteen():
    counts = {i: 2**i for i in range(40)}
    lengths = webp._huffman(counts, 280)
    assert max(lengths) <= 15 and sum(2.0**-n for n in lengths if n) == 1


def test_broken_files_raise():
    media = webp.store_bytes(webp.pad(b"x" * 3000 + bytes(range(200))))
    with pytest.raises(ValueError):
        webp.decode_image(b"RIFF" + media[4:8] + b"NOPE" + media[12:])
    short = media[:16] + (60).to_bytes(4, "little") + media[20:80]
    with pytest.raises(ValueError):
        webp.decode_image(short)
