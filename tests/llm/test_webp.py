import base64
import hashlib
import zlib

import numpy as np
import pytest

from prefpat.llm import webp

RNG = np.random.default_rng(11)


def noise(height, width, colours=None):
    pixels = RNG.integers(0, 1 << 32, (height, width), dtype=np.uint32)
    if colours:
        pixels = RNG.choice(pixels.reshape(-1)[:colours], (height, width))
    return pixels


def smooth(height, width):
    y, x = np.mgrid[:height, :width]
    return webp.joined(np.stack([np.full_like(x, 255), x * 3 + y, x + y * 2, x * y // 4], axis=-1) + RNG.integers(0, 4, (height, width, 4)))


def pictures():
    yield noise(1, 1)
    yield noise(7, 13)
    yield smooth(33, 47)
    yield np.full((20, 300), 0x80FF0102, np.uint32)
    yield noise(40, 30, 5)
    yield np.repeat(noise(10, 10), 9, axis=1)


def test_known_file():
    data = base64.b64decode("UklGRh4AAABXRUJQVlA4TBEAAAAvAAAAAAfQ//73v/+BiOh/AAA=")
    pixels, size = webp.decode_image(data)
    assert pixels.shape == (1, 1) and size == len(data)


@pytest.mark.parametrize("options", [{}, {"runs": False}, {"cache_bits": 1}, {"cache_bits": 6}, {"cache_bits": 11, "runs": False}, {"group_bits": 2}, {"group_bits": 3, "cache_bits": 4}])
def test_coding(options):
    for pixels in pictures():
        got, size = webp.decode_image(data := webp.encode_image(pixels, **options))
        assert (got == pixels).all() and size == len(data)


def test_both_decoders_agree(monkeypatch):
    for pixels in pictures():
        data = webp.encode_image(pixels, ((webp.SUBTRACT_GREEN,),))
        fast = webp.decode_image(data)[0]
        with monkeypatch.context() as m:
            m.setattr(webp, "fast_pixels", lambda reader, width, total, group: webp.plain_pixels(reader, width, total, [group], None, 0, 0))
            assert (webp.decode_image(data)[0] == fast).all()
        with monkeypatch.context() as m:
            m.setattr(webp, "SPAN_BITS", 256)
            assert (webp.decode_image(data)[0] == fast).all()


@pytest.mark.parametrize("mode", range(14))
def test_predictors(mode):
    for pixels in (noise(9, 11), smooth(21, 18), noise(1, 9), noise(9, 1)):
        modes = np.full((-(-pixels.shape[0] // 4), -(-pixels.shape[1] // 4)), mode)
        assert (webp.decode_image(webp.encode_image(pixels, ((webp.PREDICTOR, 2, modes),)))[0] == pixels).all()


def test_a_plain_reading_of_predictors():
    """Every mode's formula again, one channel and pixel at a time."""

    def guess(mode, l, t, r, c):  # noqa: E741
        half = lambda a, b: (a + b) // 2
        if mode == 11:
            to_l = sum(abs(t[i] + l[i] - c[i] - l[i]) for i in range(4))
            to_t = sum(abs(t[i] + l[i] - c[i] - t[i]) for i in range(4))
            return l if to_l < to_t else t
        one = {
            0: lambda i: (255, 0, 0, 0)[i], 1: lambda i: l[i], 2: lambda i: t[i], 3: lambda i: r[i], 4: lambda i: c[i], 5: lambda i: half(half(l[i], r[i]), t[i]), 6: lambda i: half(l[i], c[i]),
            7: lambda i: half(l[i], t[i]), 8: lambda i: half(c[i], t[i]), 9: lambda i: half(t[i], r[i]), 10: lambda i: half(half(l[i], c[i]), half(t[i], r[i])),
            12: lambda i: min(255, max(0, l[i] + t[i] - c[i])), 13: lambda i: min(255, max(0, half(l[i], t[i]) + int((half(l[i], t[i]) - c[i]) / 2))),
        }[mode]
        return [one(i) for i in range(4)]

    for mode in range(14):
        rows = RNG.integers(0, 256, (200, 4, 4)).astype(np.int32)
        got = webp.predicted(mode, *(rows[:, i] for i in range(4)))
        assert (np.broadcast_to(got, (200, 4)) == [guess(mode, *r) for r in rows.tolist()]).all(), mode


def test_all_transforms_together():
    for pixels in (noise(30, 26), smooth(50, 41)):
        shape = blocks = -(-pixels.shape[0] // 8), -(-pixels.shape[1] // 8)
        chain = ((webp.PREDICTOR, 3, RNG.integers(0, 14, shape)), (webp.CROSS_COLOUR, 3, noise(*blocks)), (webp.SUBTRACT_GREEN,))
        for options in ({}, {"cache_bits": 5, "group_bits": 2}):
            assert (webp.decode_image(webp.encode_image(pixels, chain, **options))[0] == pixels).all()


@pytest.mark.parametrize("colours", [1, 2, 3, 4, 5, 16, 17, 200])
def test_palettes(colours):
    pixels = noise(37, 51, colours)
    assert (webp.decode_image(webp.encode_image(pixels, ((webp.PALETTE,),)))[0] == pixels).all()


def test_broken_images():
    data = webp.encode_image(smooth(40, 40))
    for cut in (0, 10, 30, len(data) // 2, len(data) - 3):
        with pytest.raises((ValueError, IndexError)):
            webp.decode_image(data[:cut])
    short = bytearray(data[: len(data) // 2])
    short[4:8], short[16:20] = (len(short) - 8).to_bytes(4, "little"), (len(short) - 20).to_bytes(4, "little")
    with pytest.raises(ValueError):
        webp.decode_image(bytes(short))


def test_columns(spark, monkeypatch):
    texts = [None, "", "a", "é" * 500, "x\n" * 4000, " ".join(str(i) for i in range(30000)), "a", "\x00\x01"]
    df = spark.createDataFrame([(i, t, "z") for i, t in enumerate(texts)], "doc_id long, text string, feature string")
    rows = {r.key: r for r in webp.media_digests(df, "doc_id", "text").collect()}
    media = {r.doc_id: r.m for r in df.select("doc_id", webp.store_column(df.text).alias("m")).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        payload = raw + b"\xff" * (max(1, -(-len(raw) // 576)) * 576 - len(raw))
        r = rows[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest())
        assert r.tail_crc32 == zlib.crc32(payload[-32:])
        assert (r.media_bytes, r.media_sha256) == (len(media[i]), hashlib.sha256(media[i]).hexdigest())
    assert rows[2][1:] == rows[6][1:] and rows[0][1:] == rows[1][1:]
    back = spark.createDataFrame([(0, bytes(media[3])), (1, None)], "i int, m binary").select("i", webp.decode_column(webp.F.col("m")).alias("p")).collect()
    found = {r.i: r.p for r in back}
    assert found[0].width == 576 and found[0].height == 2 and bytes(found[0].argb)[2::4][:1000] == texts[3].encode()
    assert webp.media_digests(df.limit(0), "doc_id", "text").count() == 0
    monkeypatch.setattr(webp, "MAX_SIDE", 2)
    long = webp.padded_payload(bytes(range(256)) * 20)
    assert (webp.load(webp.store(long)) >> np.uint32(8) & np.uint32(255)).astype(np.uint8).tobytes() == long


def test_payloads_pass_every_inverse(monkeypatch):
    """Texts of a table use every transform and the cache, and come back whole."""
    used = []
    for name in ("undo_predictor", "cross_colour", "undo_palette", "shift_green"):
        whole = getattr(webp, name)
        monkeypatch.setattr(webp, name, lambda *a, name=name, whole=whole: used.append(name) or whole(*a))
    loop = webp.plain_pixels
    monkeypatch.setattr(webp, "plain_pixels", lambda *a: used.append("cache") or loop(*a))
    rng, modes = np.random.default_rng(5), set()
    for i in range(600):
        raw = " ".join("".join(map(chr, rng.integers(97, 123, 5))) for _ in range(30 + 40 * (i % 9))).encode()
        got = webp.round_trip(raw)
        payload = webp.padded_payload(raw)
        assert got[:3] == (len(raw), len(payload), hashlib.sha256(payload).hexdigest()) 
        pixels = np.frombuffer(payload, np.uint8).reshape(-1, 576).astype(np.uint32) << np.uint32(8) | np.uint32(webp.OPAQUE_BLACK)
        modes |= {int(m) for kind, *more in webp.plan_of(pixels).get("transforms", ()) if kind == webp.PREDICTOR for m in more[1].reshape(-1)}
    assert set(used) == {"undo_predictor", "cross_colour", "undo_palette", "shift_green", "cache"} and modes == {0, 1, 2, 3, 4, 8, 9}


def test_every_image_takes_a_plan():
    """No text of more than sixteen values is stored without a transform or the cache, and
    all plans come about equally often."""
    from collections import Counter

    rng, kinds = np.random.default_rng(6), Counter()
    for i in range(400):
        samples = rng.integers(97, 123, (1 + i % 3, 576)).astype(np.uint32)
        plan = webp.plan_of(samples << np.uint32(8) | np.uint32(webp.OPAQUE_BLACK))
        kinds[plan["transforms"][0][0] if "transforms" in plan else "cache" if plan.get("cache_bits") else "none"] += 1
    assert set(kinds) == {webp.PREDICTOR, webp.CROSS_COLOUR, webp.SUBTRACT_GREEN, webp.PALETTE, "cache"} and min(kinds.values()) > 400 / 16


def test_cached_images_read_at_once_and_pixel_by_pixel(monkeypatch):
    for pixels in pictures():
        for options in ({"cache_bits": 1}, {"cache_bits": 4}, {"cache_bits": 10, "runs": False}):
            data = webp.encode_image(pixels, **options)
            with monkeypatch.context() as m:
                m.setattr(webp, "SPAN_BITS", 256)
                assert (webp.decode_image(data)[0] == pixels).all()
            with monkeypatch.context() as m:
                m.setattr(webp, "plain_pixels", webp.loop_pixels)
                assert (webp.decode_image(data)[0] == pixels).all()


def test_transforms_on_packed_channels_are_the_plain_ones():
    pixels = noise(23, 31)
    c = webp.planes(pixels)
    green = c.copy()
    green[..., 1] -= c[..., 2]
    green[..., 3] -= c[..., 2]
    assert (webp.shift_green(pixels, -1) == webp.joined(green)).all() and (webp.shift_green(webp.shift_green(pixels, -1), 1) == pixels).all()
    near = [noise(23, 31) for _ in range(4)]
    for mode in range(11):
        assert (webp.predicted_numbers(mode, *near) == webp.joined(webp.predicted(mode, *map(webp.planes, near)))).all()
    for sign in (1, -1):
        e = noise(6, 8)
        want, signed = c.copy(), lambda x: (x & 255 ^ 128) - 128
        t = webp.planes(np.repeat(np.repeat(e, 4, 0), 4, 1)[:23, :31])
        want[..., 1] += sign * (signed(t[..., 3]) * signed(c[..., 2]) >> 5)
        red = want[..., 1] if sign > 0 else c[..., 1]
        want[..., 3] += sign * ((signed(t[..., 2]) * signed(c[..., 2]) >> 5) + (signed(t[..., 1]) * signed(red) >> 5))
        assert (webp.cross_colour(pixels, 2, e, sign) == webp.joined(want)).all()


def some_texts():
    rng = np.random.default_rng(8)
    yield from (None, b"", b"a", b"\xff" * 3000, bytes(range(256)) * 20, b"ab" * 4000, b"\x00" * 700)
    for i in range(60):
        letters = rng.geometric(0.07, 200 * (1 + i % 7) ** 2).clip(1, 90) + 31
        yield letters.astype(np.uint8).tobytes()


@pytest.mark.parametrize("limits", [{}, {"TOGETHER": 5000}, {"MAX_SIDE": 3}, {"PIECE_BITS": 300, "MEET_BITS": 150, "STEPS": 7}])
def test_texts_stored_and_read_together_are_those_stored_alone(monkeypatch, limits):
    """Every byte and column, and hardly any image of green alone is left to the plain form."""
    for name, value in limits.items():
        monkeypatch.setattr(webp, name, value)
    texts, found = list(some_texts()), []
    whole = webp.side_by_side
    monkeypatch.setattr(webp, "side_by_side", lambda *a: found.extend(got := whole(*a)) or got)
    assert list(webp.round_trips(texts)) == [webp.round_trip(t) for t in texts]
    assert sum(f is not None for f in found) > (0 if "PIECE_BITS" in limits else 0.8 * len(found))
    assert list(webp.round_trips([])) == []


def test_codes_of_many_are_those_of_one():
    rng = np.random.default_rng(9)
    counts = rng.geometric(0.02, (80, 280)) * (rng.random((80, 280)) < rng.random((80, 1)))
    counts[0], counts[1], counts[2, 7] = 0, 0, 5
    counts[1, 3] = 4
    counts[3, :40] = np.round(1.6 ** np.arange(40))  # deeper than a code may be
    for longest in (15, 9):
        lengths = webp.code_lengths_many(counts, longest)
        assert (lengths == [webp.code_lengths(c, longest) for c in counts]).all()
        codes, sizes = webp.code_arrays_many(lengths)
        for row, own in enumerate(lengths):
            one = webp.code_arrays(own)
            assert (codes[row] == one[0]).all() and (sizes[row] == one[1]).all()
            writer = webp.BitWriter()
            webp.write_code(writer, own)
            values, bits = webp.written_codes(lengths)[row]
            assert webp.packed(values, bits, np.cumsum(bits, dtype=np.int64) - bits)[: -(-int(bits.sum()) // 8)] == writer.to_bytes()


def test_broken_images_among_others():
    texts = [t or b"" for t in some_texts()]
    media = webp.store_all([webp.padded_payload(t) for t in texts])
    for n in (10, 20, 30, 40):
        own = bytearray(media[n])
        del own[len(own) * 2 // 3 :]
        own[4:8], own[16:20] = (len(own) - 8).to_bytes(4, "little"), (len(own) - 20).to_bytes(4, "little")
        with pytest.raises(ValueError):
            webp.load_all(media[:n] + [bytes(own)] + media[n + 1 :])


def test_a_table_takes_the_form_for_many():
    """A table's texts go through few calls: the plain form takes one or more for each text."""
    import cProfile
    import pstats

    def calls(do):
        with cProfile.Profile() as profile:
            do()
        return pstats.Stats(profile).total_calls

    texts = [t for t in some_texts() if t] * 4
    assert calls(lambda: list(webp.round_trips(texts))) * 2 < calls(lambda: [webp.round_trip(t) for t in texts])
