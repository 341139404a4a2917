import random

import numpy as np
import pytest

from graphdrift.llm import webp as w


def picture(seed, h, width, colours=None, alpha=False):
    rng = np.random.default_rng(seed)
    image = rng.integers(0, 256, (h, width, 4)).astype(np.uint8) // 16 + np.arange(width)[None, :, None].astype(np.uint8)
    image[h // 2 :] = image[: h - h // 2]
    if colours:
        palette = rng.integers(0, 256, (colours, 4)).astype(np.uint8)
        image = palette[rng.integers(0, colours, (h, width))]
    if not alpha:
        image[..., 0] = 255
    return image


def both_ways(image, **kw):
    d = w.Decoder()
    file = w.encode_image(image, **kw)
    assert (d.decode([file])[0] == image).all()
    return file


@pytest.mark.parametrize("cache", [0, 3, 11])
@pytest.mark.parametrize("matches", [False, True])
def test_pixels(cache, matches):
    for seed, (h, x) in enumerate([(1, 1), (1, 7), (9, 13), (40, 33)]):
        for alpha in (False, True):
            both_ways(picture(seed, h, x, alpha=alpha), cache_bits=cache, matches=matches)
        both_ways(picture(seed, h, x, colours=5), cache_bits=cache, matches=matches)


def test_groups():
    both_ways(picture(1, 30, 25), group_bits=2, cache_bits=4)
    both_ways(picture(1, 30, 25, alpha=True), group_bits=3)


@pytest.mark.parametrize("colours", [1, 2, 3, 4, 9, 16, 17, 256])
def test_palette(colours):
    both_ways(picture(2, 21, 19, colours=colours), transforms=((w.PALETTE,),))


def test_transforms():
    rng = np.random.default_rng(5)
    image = picture(3, 22, 37, alpha=True)
    for mode in range(14):
        both_ways(image, transforms=((w.PREDICTOR, 2, np.full((6, 10), mode, np.uint8)),))
    modes = rng.integers(0, 14, (6, 10)).astype(np.uint8)
    elements = rng.integers(0, 256, (3, 5, 4)).astype(np.uint8)
    elements[..., 0] = 255
    every = ((w.PREDICTOR, 2, modes), (w.CROSS, 3, elements), (w.GREEN,))
    both_ways(image, transforms=every, cache_bits=5, group_bits=2)
    both_ways(image, transforms=every[::-1])


def test_mixed_block_equals_single_decoding():
    d = w.Decoder()
    images = [picture(k, 1 + 3 * k, 1 + 5 * k % 40, colours=k or None, alpha=k % 2 == 0) for k in range(12)]
    files = [w.encode_image(i, cache_bits=k % 5, matches=k % 3 > 0, group_bits=2 * (k % 2), transforms=((w.GREEN,),) * (k % 2)) for k, i in enumerate(images)]
    for got, image in zip(d.decode(files), images):
        assert (got == image).all()
    for f, image in zip(files, images):
        s = d.parse(f)
        flat, _ = d._scalar(s, s.coded_width, s.height)
        assert (flat == d._side_by_side([s])[0]).all()


def test_pixels_by_hand():
    # 1 x 1, no transforms, five simple codes of one symbol each: green 2, red 1, blue 3, alpha 255
    bits = w.BitWriter()
    bits.put(0x2F, 8)
    bits.put(0, 32)
    bits.put(0, 3)
    for s in (2, 1, 3, 255, 0):
        bits.put(0b101 if s > 1 else 0b001, 3)
        bits.put(s, 8 if s > 1 else 1)
    assert w.Decoder().decode([w.wrapped(bits.bytes())])[0].tolist() == [[[255, 1, 2, 3]]]


def test_payloads():
    random.seed(1)
    texts = [b"", b"a", b"x" * 191, b"y" * 192, b"z" * 193, bytes(range(256)) * 9, ("Une phrase où tout va bien. " * 40).encode(), b"ab" * 30_000]
    texts += [bytes(random.choice(b"etaoin shrdlu\n") for _ in range(random.randint(0, 9000))) for _ in range(30)]
    for n in (7, 8, 9, 10, 31, 100):  # copies of every short length
        unit = bytes(random.choice(b"etaoin shrdlu\n") for _ in range(3 * n))
        texts.append(b"".join(unit + bytes(random.choice(b"xyz") for _ in range(9)) for _ in range(40)))
    texts += [texts[-1] * 7, bytes(random.randrange(256) for _ in range(20_000))]
    encoder, decoder = w.PayloadEncoder(), w.Decoder()
    payloads = [w.padded(t) for t in texts]
    assert all(len(p) % 192 == 0 and p for p in payloads)
    media = w.store_payloads(payloads, encoder)
    assert [p.tobytes() for p in w.load_pixels(media, decoder)] == payloads
    assert media == [w.store_payloads([p], w.PayloadEncoder())[0] for p in payloads]
    assert len(media[-2]) < len(payloads[-2]) / 3  # copies
    kinds = [[t[0] for t in s.transforms] + ["cache"] * bool(s.cache_bits) for m in media for s in map(decoder.parse, w.files_of(m))]
    assert {w.PREDICTOR, w.CROSS, w.GREEN, w.PALETTE, "cache"} == {x for k in kinds for x in k}


def test_query(spark):
    import hashlib
    import zlib

    docs = spark.createDataFrame([(1, "héllo"), (2, None), (None, "héllo")], "doc_id long, text string")
    rows = {r.doc_id: r for r in w.media_digests(docs).collect()}
    payload = "héllo".encode().ljust(192)
    assert rows[1].payload_sha256 == hashlib.sha256(payload).hexdigest() and rows[1].n_bytes == 6 and rows[1].payload_bytes == 192
    assert rows[1].tail_crc32 == zlib.crc32(payload[-16:]) and rows[1][3:] == rows[None][3:]
    assert rows[2].payload_sha256 == hashlib.sha256(b" " * 192).hexdigest() and rows[2].n_bytes == 0
    assert w.media_digests(docs.limit(0)).count() == 0


def test_every_strip_of_many_colours_goes_through_all_transforms():
    random.seed(8)
    letters = b"etaoin shrdlu cmfwyp,.\n"
    texts = [bytes(random.choice(letters) for _ in range(random.randint(1, 15_000))) for _ in range(25)] + [bytes(random.randrange(256) for _ in range(9000))]
    payloads = [w.padded(t) for t in texts]
    encoder, decoder = w.PayloadEncoder(), w.Decoder()
    for _ in range(2):  # the second time by known headers
        media = w.store_payloads(payloads, encoder)
        assert [p.tobytes() for p in w.load_pixels(media, decoder)] == payloads
    strips = [s for p in payloads for s in w.strips_of(p)]
    files = [f for m in media for f in w.files_of(m)]
    for strip, file in zip(strips, files):
        fresh = w.Decoder()
        kinds = [t[0] for t in fresh.parse(file).transforms]
        assert kinds == ([w.PALETTE] if w.PayloadEncoder._few(strip) else [w.PREDICTOR, w.CROSS, w.GREEN])
        assert fresh.decode([file])[0][..., 1:].tobytes() == strip
    assert decoder.kept > 1 and len({f[21:60] for f in files}) > 1
