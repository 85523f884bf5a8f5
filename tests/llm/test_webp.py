import numpy as np
import pytest

from relseq.llm import webp, webp_reader, webp_writer


def picture(height, width, colours, seed=0):
    draw = np.random.default_rng(seed)
    table = draw.integers(0, 256, (colours, 4), dtype=np.uint8)
    rows = table[draw.integers(0, colours, (height, width))]
    rows[height // 2 :, width // 3 :] = rows[: height - height // 2, : width - width // 3]
    return rows


@pytest.mark.parametrize("transforms", [(), (webp.GREEN,), (webp.PREDICTOR,), (webp.CROSS,), (webp.PALETTE,), (webp.PREDICTOR, webp.CROSS, webp.GREEN), (webp.PALETTE, webp.PREDICTOR)])
@pytest.mark.parametrize("colours", [1, 2, 4, 16, 200])
def test_round_trip_with_transforms(transforms, colours):
    rows = picture(13, 19, colours, colours)
    assert (webp.decode(webp.encode(rows, transforms)) == rows).all()


@pytest.mark.parametrize("tools", [{"cache_bits": 3}, {"cache_bits": 11}, {"references": True}, {"references": True, "cache_bits": 5}, {"group_bits": 2}, {"group_bits": 3, "references": True, "cache_bits": 4}])
def test_round_trip_with_tools(tools):
    for colours in (2, 40, 5000):
        rows = picture(21, 34, colours, 5)
        assert (webp.decode(webp.encode(rows, (webp.GREEN,), **tools)) == rows).all()


def test_flat_images_and_general_reading_agree():
    rgb = picture(5, 64, 300)[..., :3]
    data = webp.encode_flat(rgb)
    out = webp.decode(data)
    assert (out[..., :3] == rgb).all() and (out[..., 3] == 255).all()
    keep = webp._unpack
    try:
        webp._unpack = lambda bits, codes, n: webp._decode(bits, [codes], None, 0, 0, n, 1)
        assert (webp.decode(data) == out).all()
    finally:
        webp._unpack = keep


def test_broken_streams_are_refused():
    data = webp.encode_flat(picture(2, 64, 9)[..., :3])
    for bad in (b"", data[:40], b"JUNK" + data[4:], data[:20] + b"\x00" + data[21:]):
        with pytest.raises((ValueError, IndexError, Exception)):
            webp.decode(bad)


def test_files_in_a_row():
    a, b = webp.encode_flat(picture(1, 64, 3)[..., :3]), webp.encode_flat(picture(3, 64, 3)[..., :3])
    assert list(webp.files(a + b)) == [a, b]
    assert len(webp.NEAR) == 120 == len(set(webp.NEAR))


def samples(height, width, seed):
    draw = np.random.default_rng(seed)
    kind = seed % 6
    if kind == 0:
        return draw.integers(0, 256, (height, width, 3), dtype=np.uint8)
    if kind == 1:
        return picture(height, width, 1 + seed, seed)[..., :3]
    if kind == 2:
        return np.full((height, width, 3), seed, np.uint8)
    if kind == 3:  # smooth: predictors that look around pay
        steps = draw.integers(-2, 3, (height, width, 1))
        return (np.cumsum(np.cumsum(steps, axis=0), axis=1) + np.array([0, 3, 7])).astype(np.uint8)
    text = " ".join(f"w{i}" for i in draw.integers(0, 40 * seed, height * width)).encode()[: height * width * 3]
    return np.frombuffer(text.ljust(height * width * 3), np.uint8).reshape(height, width, 3)


@pytest.mark.parametrize("seed", range(36))
def test_stored_files_come_back(seed):
    height, width = ((1, 64), (2, 64), (9, 64), (70, 64), (200, 64), (33, 7), (5, 1), (1, 1), (130, 130))[seed % 9]
    rgb = samples(height, width, seed)
    data = webp_writer.encode(rgb)
    out = webp.decode(data)
    assert (out[..., :3] == rgb).all() and (out[..., 3] == 255).all()
    assert data == webp_writer.encode(rgb.copy())


def test_prose_takes_less_and_uses_the_tools():
    rgb = samples(200, 64, 4)
    assert len(webp_writer.encode(rgb)) < 0.8 * rgb.size
    seen = []
    keep = webp._decode_arrays
    try:
        webp._decode_arrays = lambda bits, codes, cache, *rest: seen.append((codes, cache)) or keep(bits, codes, cache, *rest)
        webp.decode(webp_writer.encode(np.concatenate([rgb, rgb])))
    finally:
        webp._decode_arrays = keep
    codes, cache = seen[-1]
    assert cache and codes[0].longest > 4 and any(codes[0].lengths[256:280])


@pytest.mark.parametrize("tools", [{}, {"cache_bits": 4}, {"references": True}, {"references": True, "cache_bits": 6}])
@pytest.mark.parametrize("window", [1, 40, 1 << 15])
def test_arrays_and_token_by_token_agree(tools, window):
    """One group of codes is read as arrays, in windows of any size, several token by token."""
    rows = picture(30, 40, 60, 9)
    data = webp.encode(rows, (webp.GREEN,), **tools)
    keep, size = webp._decode_arrays, webp.WINDOW
    try:
        webp.WINDOW = window
        assert (webp.decode(data) == rows).all()
        webp._decode_arrays = lambda bits, codes, cache, width, total: webp._decode(bits, [codes], None, 0, cache, width, total // width)
        assert (webp.decode(data) == rows).all()
    finally:
        webp._decode_arrays, webp.WINDOW = keep, size


def test_counts_that_need_long_codes():
    fib = [1, 1]
    while len(fib) < 30:
        fib.append(fib[-1] + fib[-2])
    lengths = webp_writer.code_lengths(np.array(fib), 15)
    assert lengths.max() <= 15 and sum(2.0**-n for n in lengths.tolist()) == 1


def test_batches_of_files():
    """Files do not depend on what stands beside them, and are read together as one by one."""
    shapes = [(1, 64), (2, 64), (9, 64), (70, 64), (200, 64), (33, 7), (5, 1), (1, 1), (130, 130)]
    pictures = [samples(*shapes[seed % 9], seed) for seed in range(72)]
    files = webp_writer.encode_many(pictures)
    assert files == [webp_writer.encode(p) for p in pictures]
    for out, rgb in zip(webp_reader.decode_many(files), pictures, strict=True):
        assert (out[..., :3] == rgb).all() and (out[..., 3] == 255).all()
    assert webp_writer.encode_many([]) == [] == webp_reader.decode_many([])


@pytest.mark.parametrize("entries", [1 << 22, 1 << 10])
@pytest.mark.parametrize("tools", [{}, {"cache_bits": 4}, {"references": True}, {"references": True, "cache_bits": 6}, {"group_bits": 2, "references": True, "cache_bits": 3}])
def test_reading_together_equals_reading_alone(tools, entries, monkeypatch):
    monkeypatch.setattr(webp_reader, "ALONE", 0)
    monkeypatch.setattr(webp_reader, "MOST_ENTRIES", entries)
    monkeypatch.setattr(webp_reader, "BATCH_PIXELS", 20_000)
    chosen = [(), (webp.GREEN,), (webp.PREDICTOR, webp.CROSS, webp.GREEN), (webp.PALETTE, webp.PREDICTOR)]
    pictures = [picture(3 + seed % 40, 5 + seed % 31, (1, 2, 9, 200)[seed % 4], seed) for seed in range(24)]
    files = [webp.encode(rows, chosen[seed % 4], **tools) for seed, rows in enumerate(pictures)]
    for out, rows in zip(webp_reader.decode_many(files), pictures, strict=True):
        assert (out == rows).all()
    with pytest.raises((ValueError, IndexError)):
        webp_reader.decode_many([*files[:3], files[3][:-9]])


def prose(n, seed):
    draw = np.random.default_rng(seed)
    raw = " ".join(f"w{i}" for i in draw.zipf(1.3, n) % 5000).encode()
    return np.frombuffer(raw + b" " * (-len(raw) % 192), np.uint8).reshape(-1, 64, 3)


def test_long_main_images_are_read_together(monkeypatch):
    """None of a batch's main images, however long, is read alone, nor is a single very long one."""
    alone, keep = [], webp.read_image
    monkeypatch.setattr(webp, "read_image", lambda *asked: alone.append(asked[3]) or keep(*asked))
    for pictures in ([prose(4000 + 50 * seed, seed) for seed in range(40)], [prose(80_000, 1)]):
        files = webp_writer.encode_many(pictures)
        for out, rgb in zip(webp_reader.decode_many(files), pictures, strict=True):
            assert (out[..., :3] == rgb).all()
    assert not any(alone)


@pytest.mark.parametrize("segment, stride, steps", [(40, 1, 1 << 20), (64, 16, 1 << 20), (300, 3, 1 << 20), (1 << 20, 16, 1 << 20), (64, 4, 4), (2048, 16, 160)])
def test_entries_anywhere_give_the_same_tokens(segment, stride, steps, monkeypatch):
    """Wherever streams are entered, and where entries do not meet in time."""
    for name, value in (("ALONE", 0), ("SEGMENT", segment), ("STRIDE", stride), ("MOST_STEPS", steps)):
        monkeypatch.setattr(webp_reader, name, value)
    pictures = [prose(20 + 40 * seed, seed) for seed in range(30)] + [samples(70, 64, seed) for seed in range(12)]
    files = webp_writer.encode_many(pictures)
    every = [picture(9 + seed, 40, (3, 90, 5000)[seed % 3], seed) for seed in range(12)]
    files += [webp.encode(rows, (webp.GREEN,), references=seed % 2 == 0, cache_bits=seed % 5) for seed, rows in enumerate(every)]
    files += [webp.encode_flat(p) for p in pictures[:3]]
    for out, want in zip(webp_reader.decode_many(files), pictures + every + pictures[:3], strict=True):
        assert (out[..., : want.shape[2]] == want).all()


def test_entries_that_never_meet_the_right_one(monkeypatch):
    """Codes of nearly one width: entries meet each other, not the chain from the first bit."""
    reads, keep = [], webp_reader._leave
    monkeypatch.setattr(webp_reader, "ALONE", 0)
    monkeypatch.setattr(webp_reader, "_leave", lambda *a: reads.append(1) or keep(*a))
    rgb = np.random.default_rng(5).integers(0, 256, (4000, 64, 3), dtype=np.uint8)
    [out] = webp_reader.decode_many(webp_writer.encode_many([rgb]))
    assert (out[..., :3] == rgb).all() and len(reads) <= 1 + webp_reader.MOST_ROUNDS


def test_trees_alone_and_side_by_side_are_equal(monkeypatch):
    draw = np.random.default_rng(3)
    counts = [draw.zipf(1.2, 2 + 9 * k).clip(0, 10_000) for k in range(80)]
    flat, sizes = np.concatenate(counts), np.array([len(c) for c in counts])
    got = webp_writer.code_lengths(flat, 15, sizes)
    for large, least in ((0, 0), (1 << 20, 1 << 20), (5, 8)):
        monkeypatch.setattr(webp_writer, "LARGE", large)
        monkeypatch.setattr(webp_writer, "LEAST_LARGE", least)
        assert (webp_writer.code_lengths(flat, 15, sizes) == got).all()


def test_palettes_are_weighed_together():
    """A picture's file is the same whether its colours are counted with those of others or alone."""
    pictures = [picture(h, 64, colours, h + colours)[..., :3] for h in (1, 3, 30) for colours in (1, 2, 5, 17, 200, 256, 257, 900)]
    files = webp_writer.encode_many(pictures)
    assert files == [webp_writer.encode(p) for p in pictures]
    kinds = {webp.Bits(webp.content(f), 41).peek(2) for f in files}
    assert kinds == {webp.PREDICTOR, webp.PALETTE}
    for out, rgb in zip(webp_reader.decode_many(files), pictures, strict=True):
        assert (out[..., :3] == rgb).all()
