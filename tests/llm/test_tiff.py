import hashlib
import struct
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from recordlink.llm import tiff

RNG = np.random.default_rng(5)


@settings(max_examples=150, deadline=None)
@given(st.one_of(st.binary(max_size=600), st.text("ab", max_size=900).map(str.encode), st.builds(lambda b, n: b * n, st.binary(min_size=1, max_size=3), st.integers(1, 9000))))
def test_codecs_round_trip(data):
    for codec in (tiff.NONE, tiff.PACKBITS, tiff.LZW, tiff.DEFLATE):
        assert tiff.decode(tiff.encode(data, codec), codec, len(data)) == data


def test_lzw_across_table_resets():
    data = RNG.integers(0, 256, 60_000).astype(np.uint8).tobytes()
    assert tiff.lzw_decode(tiff.lzw_encode(data), len(data)) == data


def test_lzw_known_stream():
    """7 7 7 8 8 7 7 6 6, a worked example of the format's description."""
    codes = [256, 7, 258, 8, 8, 258, 6, 6, 257]
    bits = "".join(f"{c:09b}" for c in codes)
    raw = bytes(int(bits[i : i + 8].ljust(8, "0"), 2) for i in range(0, len(bits), 8))
    assert tiff.lzw_encode(bytes([7, 7, 7, 8, 8, 7, 7, 6, 6])) == raw
    assert tiff.lzw_decode(raw, 9) == bytes([7, 7, 7, 8, 8, 7, 7, 6, 6])


def test_packbits_known_stream():
    packed = bytes.fromhex("FE AA 02 80 00 2A FD AA 03 80 00 2A 22 F7 AA")
    plain = bytes.fromhex("AA AA AA 80 00 2A AA AA AA AA 80 00 2A 22 AA AA AA AA AA AA AA AA AA AA")
    assert tiff.packbits_decode(packed) == plain and tiff.packbits_encode(plain) == packed


@pytest.mark.parametrize("order", "<>")
@pytest.mark.parametrize("tile", [None, (16, 32)])
@pytest.mark.parametrize("predictor", [1, 2])
def test_files_round_trip(order, tile, predictor):
    images = [RNG.integers(0, 256, s).astype(np.uint8) for s in ((70, 45), (1, 1), (33, 64, 3), (300, 64))]
    for codec in (tiff.NONE, tiff.PACKBITS, tiff.LZW, tiff.DEFLATE):
        got = list(tiff.pages(tiff.write(images, [codec] * 4, predictor, 20, tile, order)))
        assert len(got) == 4
        for (pixels, about, error), image in zip(got, images, strict=True):
            assert error is None and (pixels.reshape(image.shape) == image).all()
            assert about["layout"] == ("tiles" if tile else "strips") and about["compression"] == codec


def test_big_planar_and_16_bit():
    """Files that the writer does not make, put together by hand."""
    a = RNG.integers(0, 65536, (3, 5)).astype(">u2")
    data = bytearray(b"MM" + struct.pack(">HHHQ", 43, 8, 0, 16))
    tags = [(256, 3, 5), (257, 3, 3), (258, 3, 16), (259, 3, 1), (273, 16, 16 + 8 + 20 * 7 + 8), (278, 3, 3), (279, 4, 30)]
    data += struct.pack(">Q", len(tags))
    for t, k, v in tags:
        data += struct.pack(">HHQ", t, k, 1) + (struct.pack(">HHHH", v, 0, 0, 0) if k == 3 else struct.pack(">II", v, 0) if k == 4 else struct.pack(">Q", v))
    data += struct.pack(">Q", 0) + a.tobytes()
    ((pixels, about, error),) = tiff.pages(bytes(data))
    assert error is None and (pixels[:, :, 0] == a).all() and about["bits"] == 16


def test_faults_give_one_row():
    good = tiff.write([np.zeros((4, 4), np.uint8)] * 2, [tiff.DEFLATE] * 2)
    for bad in (None, b"", b"II", b"GIF89a..", good[:20], good[:-20]):
        got = list(tiff.pages(bad))
        assert got[-1][2] and got[-1][0] is None
    loop = bytearray(tiff.write([np.zeros((4, 4), np.uint8)], [tiff.NONE]))
    (first,) = struct.unpack_from("<I", loop, 4)
    struct.pack_into("<I", loop, len(loop) - 4, first)
    assert [e for _, _, e in tiff.pages(bytes(loop))] == [None, "directories in a circle"]
    assert list(tiff.pages(good, max_bytes=10))[0][2] == "a page larger than max_bytes"


def test_rows_for_pages(spark):
    files = [(1, tiff.write([np.full((2, 3), 9, np.uint8), np.eye(4, dtype=np.uint8)], [tiff.LZW, tiff.PACKBITS])), (2, None), (3, b"nothing")]
    df = spark.createDataFrame([(i, d, "w") for i, d in files], "doc_id long, data binary, width string")
    rows = sorted(tiff.explode_pages(df, ["doc_id", "width"]).collect(), key=lambda r: (r["doc_id"], r["page"]))
    assert [(r["doc_id"], r["page"], r["width"], bool(r["error"])) for r in rows] == [(1, 0, 3, False), (1, 1, 4, False), (2, 0, None, True), (3, 0, None, True)]
    assert bytes(rows[0]["pixels"]) == b"\x09" * 6 and rows[0]["width_in"] == "w"
    assert tiff.explode_pages(df.where("false"), ["doc_id"]).count() == 0


def brute(text):
    raw = (text or "").encode()
    full = raw + b"\0" * (-len(raw) % 64)
    full = full or b"\0" * 64
    return len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-64:])


def test_every_text_comes_back(docs, odd, none):
    for df in (docs, odd):
        rows = tiff.text_media(df, keep=("doc_id", "text")).collect()
        assert len(rows) == df.count()
        by_text = {}
        for r in rows:
            assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == brute(r["text"])
            assert hashlib.sha256(tiff.store(tiff.payload((r["text"] or "").encode()))).hexdigest() == r["media_sha256"]
            assert by_text.setdefault(r["text"] or "", (r["media_sha256"], r["feature"])) == (r["media_sha256"], r["feature"])
    assert tiff.text_media(none).count() == 0


def test_pages_after_a_faulty_one_are_read():
    images = [np.full((4, 6), k, np.uint8) for k in range(3)]
    data = bytearray(tiff.write(images, [tiff.DEFLATE] * 3))
    (at,) = struct.unpack_from("<I", data, 4)
    (n,) = struct.unpack_from("<H", data, at)
    (at,) = struct.unpack_from("<I", data, at + 2 + 12 * n)
    (n,) = struct.unpack_from("<H", data, at)
    for k in range(n):
        if struct.unpack_from("<H", data, at + 2 + 12 * k) == (259,):
            struct.pack_into("<H", data, at + 2 + 12 * k + 8, 999)
    got = list(tiff.pages(bytes(data)))
    assert [e is None for _, _, e in got] == [True, False, True]
    assert (got[2][0].squeeze() == 2).all()


def other_reader(data):
    """A second reader, by strings of bits and plain lists, of what the writer makes: little-endian classic files of 8-bit grey pages."""
    (at,) = struct.unpack_from("<I", data, 4)
    while at:
        (n,) = struct.unpack_from("<H", data, at)
        tags = {}
        for k in range(n):
            tag, kind, count = struct.unpack_from("<HHI", data, at + 2 + 12 * k)
            size = {3: 2, 4: 4}[kind] * count
            place = at + 10 + 12 * k if size <= 4 else struct.unpack_from("<I", data, at + 10 + 12 * k)[0]
            tags[tag] = struct.unpack_from(f"<{count}{'H' if kind == 3 else 'I'}", data, place)
        (at,) = struct.unpack_from("<I", data, at + 2 + 12 * n)
        (width,), (height,), (codec,) = tags[256], tags[257], tags[259]
        tiled = 322 in tags
        bw, bh = (tags[322][0], tags[323][0]) if tiled else (width, tags[278][0])
        grid = [[0] * width for _ in range(height)]
        across = -(-width // bw)
        for k, (lo, size) in enumerate(zip(*((tags[324], tags[325]) if tiled else (tags[273], tags[279])), strict=True)):
            raw, plain = data[lo : lo + size], []
            if codec == 8:
                plain = list(zlib.decompress(raw))
            elif codec == 32773:
                i = 0
                while i < len(raw):
                    c = raw[i]
                    plain += raw[i + 1 : i + 2 + c] if c < 128 else raw[i + 1 : i + 2] * (257 - c)
                    i += 2 + c if c < 128 else 2
            else:
                bits, p, size, table, prev = "".join(f"{b:08b}" for b in raw), 0, 9, {}, None
                while True:
                    c, p = int(bits[p : p + size], 2), p + size
                    if c == 257:
                        break
                    if c == 256:
                        table, size, prev = {i: [i] for i in range(256)}, 9, None
                        continue
                    entry = table[c] if c in table else prev + prev[:1]
                    if prev is not None:
                        table[len(table) + 2] = prev + entry[:1]
                    size = 9 + sum(len(table) + 3 >= x for x in (512, 1024, 2048))
                    plain += entry
                    prev = entry
            y0, x0 = k // across * bh, k % across * bw
            for y in range(min(bh, height - y0)):
                total = 0
                for x in range(min(bw, width - x0)):
                    total = (total + plain[y * bw + x]) % 256 if tags[317] == (2,) else plain[y * bw + x]
                    grid[y0 + y][x0 + x] = total
        yield codec, tiled, bytes(x for row in grid for x in row)


def test_every_file_has_all_codecs_and_layouts_whatever_its_size():
    kinds = set()
    for n in (0, 1, 63, 64, 65, 1000, 2049, 70_000, 300_000):
        for seed in range(4):
            text = bytes(np.random.default_rng(n + seed).choice(list(b"etaoin shrdlu\n"), n))
            data = tiff.payload(text)
            got = list(other_reader(tiff.store(data)))
            assert b"".join(p for _, _, p in got) == data
            assert {c for c, _, _ in got} == {tiff.LZW, tiff.PACKBITS, tiff.DEFLATE} and {t for _, t, _ in got} == {True, False}
            kinds |= {(c, t) for c, t, _ in got}
    assert len(kinds) == 6


def test_lzw_tables_that_are_never_cleared():
    """A stream that goes on at twelve bits after its table is full."""
    data = RNG.integers(0, 4, 50_000).astype(np.uint8).tobytes()
    table, codes, word = {bytes([i]): i for i in range(256)}, [256], b""
    for b in data:
        if word + bytes([b]) in table:
            word += bytes([b])
            continue
        codes.append(table[word])
        if len(table) < 4094:
            table[word + bytes([b])] = len(table) + 2
        word = bytes([b])
    codes += [table[word], 257]
    bits = "".join(f"{c:0{9 if k == 0 else min(12, (257 + k).bit_length())}b}" for k, c in enumerate(codes))
    raw = bytes(int(bits[i : i + 8].ljust(8, "0"), 2) for i in range(0, len(bits), 8))
    assert len(codes) > 4200 and tiff.lzw_decode(raw, len(data)) == data


def test_kept_names_clash_at_every_level(spark):
    df = spark.createDataFrame([(1, "text", 2, 3, 4)], "doc_id long, text string, feature int, feature_in int, Feature_in_in int")
    got = tiff.text_media(df, keep=("doc_id", "feature", "feature_in", "Feature_in_in"))
    assert len({c.lower() for c in got.columns}) == len(got.columns)
    row = got.first().asDict()
    assert sorted(v for v in row.values() if isinstance(v, int) and v in (2, 3, 4)) == [2, 3, 4, 4] or {2, 3, 4} <= set(row.values())


def test_a_very_long_text(spark):
    text = "".join(f"line {i} of a long text\n" for i in range(120_000))
    row = tiff.text_media(spark.createDataFrame([("a", text)], "doc_id string, text string")).first()
    assert (row["n_bytes"], row["payload_bytes"], row["payload_sha256"], row["tail_crc32"]) == brute(text) and row["n_pages"] > 20
