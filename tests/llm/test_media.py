import hashlib
import zlib

import numpy as np
import pytest

from structcurve.llm import webp

RNG = np.random.default_rng(0)
NOISE = RNG.integers(0, 256, (37, 45, 3)).astype(np.uint8)
CALM = (RNG.integers(0, 3, (37, 45, 3)) * 40).astype(np.uint8)
FEW = np.array([[10, 20, 30], [40, 50, 60], [1, 2, 3], [255, 0, 9]], np.uint8)[RNG.integers(0, 4, (13, 21))]
FLAT = np.full((5, 7, 3), 9, np.uint8)
CASES = [(NOISE, {}), (FLAT, {}), (NOISE, {"subtract_green": True}), (NOISE, {"cross_colour": (5, -70, 100)}), (CALM, {"matches": True}), (CALM, {"matches": True, "cache_bits": 4}), (CALM, {"cache_bits": 8}), (FEW, {"palette": True}), (FEW[:, :, :] // 255, {"palette": True, "matches": True}), (CALM, {"palette": True, "cache_bits": 3}), (CALM, {"matches": True, "cache_bits": 6, "subtract_green": True, "cross_colour": (9, -9, 33), "predictor": 11})] + [(CALM, {"predictor": m}) for m in range(14)]


@pytest.mark.parametrize("image,options", CASES)
def test_round_trip(image, options):
    back = webp.decode(webp.encode(image, **options))
    assert (back[..., :3] == image).all() and (back[..., 3] == 255).all()


def test_alpha():
    back = webp.decode(webp.encode(NOISE, alpha=NOISE[..., 0].copy()))
    assert (back[..., 3] == NOISE[..., 0]).all()


def test_near_distances_are_the_formats():
    assert len(webp.NEAR) == 120
    assert webp.NEAR[:8] == [(0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2)] and webp.NEAR[-3:] == [(-7, 7), (8, 6), (8, 7)]


def test_code_lengths_stay_within_the_limit():
    counts = np.array([int(1.7**i) for i in range(40)])
    for limit in (7, 15):
        n = webp.code_lengths(counts, limit)
        assert n.max() <= limit and sum(2.0**-int(x) for x in n) == 1


@pytest.mark.parametrize("n", [0, 1, 575, 576, 577, 100_000, 2_000_003])
def test_payloads(n):
    raw = (b"some text, over and over; " * (n // 26 + 1))[:n]
    payload = webp.padded(raw)
    assert len(payload) % 576 == 0 and payload[:n] == raw and set(payload[n:]) <= {255}
    assert webp.load(webp.store(payload)).tobytes() == payload


def test_long_payloads_take_several_files(monkeypatch):
    monkeypatch.setattr(webp, "MAX_SIDE", 200)
    payload = webp.padded(bytes(range(256)) * 600)
    media = webp.store(payload)
    assert media.count(b"VP8L") >= 2 and webp.load(media).tobytes() == payload


@pytest.mark.parametrize("cut", [10, 40, 200])
def test_broken_files_raise(cut):
    with pytest.raises((ValueError, IndexError)):
        webp.decode(webp.encode(NOISE)[:cut])


ROWS = np.tile(RNG.integers(0, 256, (3, 45, 3)), (12, 1, 1)).astype(np.uint8)
TEXT = np.frombuffer((b"a line of text that comes again, " * 30 + bytes(RNG.integers(97, 123, 600, dtype=np.uint8))) * 5, np.uint8)[:7200].reshape(50, 48, 3)


@pytest.mark.parametrize("image", [NOISE, CALM, FEW, FLAT, ROWS, np.repeat(NOISE[:1], 20, axis=0), TEXT, NOISE[:1, :1], np.concatenate([NOISE, NOISE])])
def test_the_encoder_picks_what_pays(image):
    plain, best = webp.encode(image), webp.encode(image, best=True)
    assert (webp.decode(best)[..., :3] == image).all() and len(best) <= len(plain) + 8


def test_what_is_picked():
    """Kinds of transforms and copies in the files that the encoder writes."""

    def kinds(data):
        bits, out = webp.BitReader(data[20:]), []
        bits.read(40)
        if bits.read(1):
            out.append(bits.read(2))
        return out

    assert kinds(webp.encode(FLAT, best=True)) == kinds(webp.encode(FEW, best=True)) == [webp.PALETTE]
    assert kinds(webp.encode(np.repeat(NOISE[:1], 20, axis=0), best=True)) == [webp.PREDICTOR]
    assert len(webp.encode(TEXT, best=True)) < 0.5 * len(webp.encode(TEXT))
    assert len(webp.encode(ROWS, best=True)) < 0.3 * len(webp.encode(ROWS))


def test_repeats_occur_before():
    v = np.concatenate([RNG.integers(0, 9, 500), np.zeros(9000, np.int64), RNG.integers(0, 9, 300)])
    v = np.concatenate([v, v[100:400], v[50:90]])
    found, end = webp.repeats(v), 0
    for at, n, d in found:
        assert at >= end and 0 < n <= 4096 and d >= 1 and all(v[i] == v[i - d] for i in range(at, at + n))
        end = at + n
    assert sum(n for _, n, _ in found) > 9000


#: Files written by other hands.  The first is the public one-pixel file by which browsers are tested for
#: lossless WebP; the second is written out bit by bit from the format: 3 x 1 pixels, green 7 and two copies of it.
ONE_PIXEL = "UklGRhoAAABXRUJQVlA4TA0AAAAvAAAAEAcQERGIiP4HAA=="


def test_a_file_of_another_encoder():
    import base64

    got = webp.decode(base64.b64decode(ONE_PIXEL))
    assert got.shape == (1, 1, 4) and got.tolist() == [[[0, 0, 0, 0]]]


def test_a_file_written_by_hand():
    bits = "11110100" + format(2, "014b")[::-1] + format(0, "014b")[::-1] + "0" + "000" + "0"  # 0x2f, sides, alpha, version, no transform
    bits += "0" + "0"  # no cache, one group
    # green: normal code; 5 lengths of the length code (17, 18, 0, 1, 2): 18 -> 2 bits, 0 -> 2 bits, 1 -> 1 bit
    bits += "0" + format(1, "04b")[::-1] + "000" + "010" + "010" + "100" + "000" + "0"
    one, zero, many = "0", "10", "11"  # canonical codes, first bit first
    run = lambda n: many + format(n - 11, "07b")[::-1]
    bits += zero * 7 + one + run(138) + run(110) + zero + one + run(22)  # lengths: 7 -> 1, 257 -> 1
    for value in (1, 2, 255):  # red, blue, alpha: one symbol each
        bits += "1" + "0" + "1" + format(value, "08b")[::-1]
    bits += "1" + "0" + "0" + "1"  # distances: the symbol 1, code 2, the pixel to the left
    bits += "0" + "1"  # green 7, then length symbol 1: two pixels
    body = bytes(int(bits[i : i + 8].ljust(8, "0")[::-1], 2) for i in range(0, len(bits), 8))
    chunk = b"VP8L" + len(body).to_bytes(4, "little") + body + b"\0" * (len(body) & 1)
    got = webp.decode(b"RIFF" + (4 + len(chunk)).to_bytes(4, "little") + b"WEBP" + chunk)
    assert got.tolist() == [[[1, 7, 2, 255]] * 3]


def brute_feature(payload):
    """The description by plain loops over the samples."""
    import math
    from collections import Counter

    n = len(payload)
    means = [sum(payload[c::3]) * 1000 // (n // 3) for c in range(3)]
    entropy = round(-sum(k / n * math.log2(k / n) for k in Counter(payload).values()) * 1000)
    height, cells = n // 576, []
    edge = [r * height // 8 for r in range(8)] + [height]
    for r in range(8):
        rows = range(edge[r], max(edge[r] + 1, edge[r + 1]))
        cells += [sum(sum(payload[y * 576 + x * 72 : y * 576 + x * 72 + 72]) for y in rows) / len(rows) for x in range(8)]
    middle = sorted(cells)
    median = (middle[31] + middle[32]) / 2
    return f"rgb={means[0]},{means[1]},{means[2]};entropy={entropy};hash={int(''.join(str(int(c > median)) for c in cells), 2):016x}"


@pytest.mark.parametrize("n", [0, 10, 577, 5000, 40_000])
def test_feature_against_loops(n):
    payload = webp.padded(bytes(RNG.integers(32, 127, n, dtype=np.uint8)))
    assert webp.describe(webp.load(webp.store(payload))) == brute_feature(payload)


def test_operator(spark):
    rows = spark.createDataFrame([(1, "héllo " * 500), (2, "héllo " * 500)], "doc_id bigint, text string")
    media = webp.media_column(rows)
    one, two = media.collect()
    payload = webp.padded(("héllo " * 500).encode())
    assert bytes(one.pixels) == payload and one.height * one.width * 3 == len(payload) and tuple(one)[1:] == tuple(two)[1:]
    a, b = webp.media_digests(media).collect()
    assert a.payload_sha256 == hashlib.sha256(payload).hexdigest() and a.tail_crc32 == zlib.crc32(payload[-32:])
    assert (a.payload_bytes, a.media_bytes, a.media_sha256) == (len(payload), len(one.media), hashlib.sha256(one.media).hexdigest()) and tuple(a)[1:] == tuple(b)[1:]
