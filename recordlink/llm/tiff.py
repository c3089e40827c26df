"""TIFF files: image directories, strips and tiles, PackBits, LZW and deflate, predictors; one row a page.

Reader: classic and big files in either byte order, 8- and 16-bit samples, chunky or planar layout.  A
page that cannot be decoded gives a row with ``error``; the pages before it stay.  Writer: 8-bit
grey or chunky pages, as strips or tiles, under any of the codecs.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import common

NONE, LZW, DEFLATE, PACKBITS, OLD_DEFLATE = 1, 5, 8, 32773, 32946
#: The tags read here, by number.
TAGS = {256: "width", 257: "height", 258: "bits", 259: "compression", 262: "photometric", 273: "strip_offsets", 277: "samples", 278: "rows_per_strip", 279: "strip_counts", 284: "planar", 317: "predictor", 322: "tile_width", 323: "tile_height", 324: "tile_offsets", 325: "tile_counts", 339: "sample_format"}
#: The struct letters of field types.
KINDS = {1: "B", 2: "s", 3: "H", 4: "I", 6: "b", 7: "s", 8: "h", 9: "i", 13: "I", 16: "Q", 17: "q", 18: "Q"}


class TiffError(ValueError):
    pass


# ------------------------------------------------------------------ codecs


def packbits_decode(data: bytes) -> bytes:
    out, i, n = [], 0, len(data)
    while i < n:
        head = data[i]
        if head < 128:
            out.append(data[i + 1 : i + 2 + head])
            i += 2 + head
        elif head > 128:
            out.append(data[i + 1 : i + 2] * (257 - head))
            i += 2
        else:
            i += 1
    return b"".join(out)


def packbits_encode(data: bytes) -> bytes:
    """Runs of three or more equal bytes as repeats, all else as literals."""
    if not data:
        return b""
    a = np.frombuffer(data, np.uint8)
    edge = np.flatnonzero(np.concatenate(([True], a[1:] != a[:-1], [True])))
    long = np.flatnonzero(np.diff(edge) >= 3)  # texts have few runs: only they are looped over
    out, at = [], 0

    def literal(raw: bytes) -> None:
        for k in range(0, len(raw), 128):
            part = raw[k : k + 128]
            out.append(bytes([len(part) - 1]) + part)

    for lo, hi in zip(edge[long].tolist(), edge[long + 1].tolist(), strict=True):
        literal(data[at:lo])
        for k in range(lo, hi, 128):
            run = min(hi - k, 128)
            out.append(bytes([257 - run if run > 1 else 0, data[lo]]))
        at = hi
    literal(data[at:])
    return b"".join(out)


#: Bits of the codes after a clear code, in order: one entry early, twelve at most.
CODE_BITS = np.array([min(12, (258 + j).bit_length()) for j in range(4096)])
SINGLE = [bytes([i]) for i in range(256)] + [b"", b""]


def _codes(data: np.ndarray, at: int) -> np.ndarray:
    """The codes from bit ``at`` up to the next clear or end code, or to the data's end, as if each follows a clear code."""
    got = []
    while True:
        most = min(4096, 8 * len(data) // 9)
        bits = CODE_BITS[:most] if not got else CODE_BITS[-1:].repeat(most)
        start = at + np.cumsum(bits) - bits
        start = start[start + bits <= 8 * (len(data) - 2)]  # two bytes were put at the end
        bits = bits[: len(start)]
        byte = start >> 3
        window = data[byte].astype(np.int64) << 16 | data[byte + 1].astype(np.int64) << 8 | data[byte + 2]
        codes = window >> 24 - (start & 7) - bits & (1 << bits) - 1
        ends = np.flatnonzero((codes == 256) | (codes == 257))
        got.append(codes[: ends[0] + 1] if len(ends) else codes)
        if len(ends) or len(codes) < 4096:
            return np.concatenate(got)
        at = int(start[-1] + bits[-1])


def lzw_decode(data: bytes, limit: int) -> bytes:
    """At most ``limit`` bytes; codes are read most significant bit first and grow one entry early."""
    raw = np.frombuffer(data + b"\0\0", np.uint8)
    at, out, size = 0, [], 0
    while size < limit:
        codes = _codes(raw, at)
        if not len(codes):
            break
        at += int(CODE_BITS[: len(codes)].sum()) + 12 * max(0, len(codes) - 4096)
        last = int(codes[-1])
        run = codes[:-1].tolist() if last in (256, 257) else codes.tolist()
        if run:
            if run[0] > 255:
                raise TiffError("LZW: a first code beyond the bytes")
            table, known = SINGLE[:], 258
            prev = table[run[0]]
            made = [prev]
            add, put = table.append, made.append
            for code in run[1:]:
                if code < known:
                    entry = table[code]
                elif code == known:
                    entry = prev + prev[:1]
                else:
                    raise TiffError("LZW: a code ahead of the table")
                if known < 4096:
                    add(prev + entry[:1])
                    known += 1
                put(entry)
                prev = entry
            part = b"".join(made)
            out.append(part)
            size += len(part)
        if last != 256:
            break
    return b"".join(out)[:limit]


def lzw_encode(data: bytes) -> bytes:
    """A clear code, codes, an end code; the table is cleared when it is full."""
    codes, starts = [256], [1]  # starts: where a count of bits begins anew
    table: dict[int, int] = {}
    known, add, fresh = table.get, codes.append, 258
    code = data[0] if data else -1
    for byte in data[1:]:
        key = code << 8 | byte
        found = known(key)
        if found is not None:
            code = found
            continue
        add(code)
        table[key] = fresh
        fresh += 1
        if fresh == 4095:
            add(256)
            starts.append(len(codes))
            table.clear()
            fresh = 258
        code = byte
    if code >= 0:
        add(code)
    codes.append(257)
    first = np.array(starts)
    place = np.arange(len(codes)) - first[np.maximum(np.searchsorted(first, np.arange(len(codes)), side="right") - 1, 0)]
    bits = CODE_BITS[np.maximum(place, 0)]
    end = np.cumsum(bits)
    at = end - bits
    value = np.array(codes, np.int64) << 24 - (at & 7) - bits
    size = int(end[-1]) + 7 >> 3
    packed = sum(np.bincount((at >> 3) + k, weights=value >> 16 - 8 * k & 0xFF, minlength=size + 2) for k in range(3))
    return packed[:size].astype(np.uint8).tobytes()


def _inflate(data: bytes, limit: int) -> bytes:
    try:
        return zlib.decompressobj().decompress(data, max(1, limit))
    except zlib.error as e:
        raise TiffError(f"deflate: {e}") from None


def decode(data: bytes, codec: int, limit: int) -> bytes:
    if codec == NONE:
        return data[:limit]
    if codec == PACKBITS:
        return packbits_decode(data)[:limit]
    if codec == LZW:
        return lzw_decode(data, limit)
    if codec in (DEFLATE, OLD_DEFLATE):
        return _inflate(data, limit)
    raise TiffError(f"compression {codec} is not known")


def encode(data: bytes, codec: int) -> bytes:
    return {NONE: bytes, PACKBITS: packbits_encode, LZW: lzw_encode, DEFLATE: lambda x: zlib.compress(x, 6)}[codec](data)


# ------------------------------------------------------------------ files


def _directory(data: bytes, at: int, order: str, big: bool) -> tuple[dict[str, list[int]], int]:
    """The known tags of a directory, and where the next one is (0: none)."""
    size, count, step = (8, "Q", 20) if big else (2, "H", 12)
    (n,) = struct.unpack_from(order + count, data, at)
    tags: dict[str, list[int]] = {}
    for i in range(n):
        here = at + size + i * step
        tag, kind = struct.unpack_from(order + "HH", data, here)
        (number,) = struct.unpack_from(order + ("Q" if big else "I"), data, here + 4)
        if tag not in TAGS or kind not in KINDS:
            continue
        letter = KINDS[kind]
        value, room = here + (12 if big else 8), 8 if big else 4
        if struct.calcsize(letter) * number > room:
            (value,) = struct.unpack_from(order + ("Q" if big else "I"), data, value)
        if value + struct.calcsize(letter) * number > len(data):
            raise TiffError("a tag's values lie beyond the file")
        tags[TAGS[tag]] = list(struct.unpack_from(f"{order}{number}{letter}", data, value))
    (after,) = struct.unpack_from(order + ("Q" if big else "I"), data, at + size + n * step)
    return tags, after


def _unpredict(block: np.ndarray, predictor: int) -> np.ndarray:
    """block: rows x columns x samples."""
    if predictor == 1:
        return block
    if predictor == 2:
        return np.cumsum(block, axis=1, dtype=block.dtype)
    raise TiffError(f"predictor {predictor} is not known")


def _predict(block: np.ndarray) -> np.ndarray:
    out = block.copy()
    out[:, 1:] = block[:, 1:] - block[:, :-1]
    return out


def _page(data: bytes, tags: dict[str, list[int]], order: str, max_bytes: int) -> tuple[np.ndarray, dict]:
    one = lambda k, d: (tags.get(k) or [d])[0]
    width, height, samples = one("width", 0), one("height", 0), one("samples", 1)
    bits, codec, predictor, planar = tags.get("bits") or [1], one("compression", 1), one("predictor", 1), one("planar", 1)
    if width <= 0 or height <= 0 or samples <= 0:
        raise TiffError("a page without pixels")
    if any(b != bits[0] for b in bits) or bits[0] not in (8, 16):
        raise TiffError(f"samples of {bits} bits are not known")
    dtype = np.dtype(np.uint8) if bits[0] == 8 else np.dtype(np.uint16).newbyteorder(order)
    if width * height * samples * dtype.itemsize > max_bytes:
        raise TiffError("a page larger than max_bytes")
    tiled = "tile_offsets" in tags
    bw, bh = (one("tile_width", 0), one("tile_height", 0)) if tiled else (width, min(one("rows_per_strip", height), height))
    offsets, counts = (tags.get("tile_offsets"), tags.get("tile_counts")) if tiled else (tags.get("strip_offsets"), tags.get("strip_counts"))
    if bw <= 0 or bh <= 0 or not offsets or not counts:
        raise TiffError("no strips or tiles")
    across, down = -(-width // bw), -(-height // bh)
    planes, depth = (samples, 1) if planar == 2 else (1, samples)
    if len(offsets) < across * down * planes or len(counts) < across * down * planes:
        raise TiffError("too few strips or tiles")
    out = np.zeros((height, width, samples), dtype.newbyteorder("="))
    for k in range(across * down * planes):
        plane, rest = divmod(k, across * down)
        y, x = rest // across * bh, rest % across * bw
        rows = bh if tiled else min(bh, height - y)
        need = rows * bw * depth * dtype.itemsize
        if offsets[k] + counts[k] > len(data):
            raise TiffError("a strip or tile beyond the file")
        raw = decode(data[offsets[k] : offsets[k] + counts[k]], codec, need)
        if len(raw) < need:
            raise TiffError("a strip or tile is short")
        block = _unpredict(np.frombuffer(raw, dtype, rows * bw * depth).astype(dtype.newbyteorder("=")).reshape(rows, bw, depth), predictor)
        part = block[: height - y, : width - x]
        out[y : y + part.shape[0], x : x + part.shape[1], plane : plane + depth] = part
    about = {"width": width, "height": height, "samples": samples, "bits": bits[0], "compression": codec, "predictor": predictor, "layout": "tiles" if tiled else "strips", "blocks": across * down * planes}
    return out, about


def pages(data: bytes | None, max_bytes: int = 1 << 28) -> Iterator[tuple[np.ndarray | None, dict, str | None]]:
    """(pixels, facts, error) of each page in directory order; a page's fault is its row, a fault of the directories ends the walk."""
    if not data or len(data) < 8 or data[:2] not in (b"II", b"MM"):
        yield None, {}, "not a TIFF file"
        return
    order = "<" if data[:2] == b"II" else ">"
    (magic,) = struct.unpack_from(order + "H", data, 2)
    if magic not in (42, 43):
        yield None, {}, "not a TIFF file"
        return
    big, seen = magic == 43, set()
    try:
        (at,) = struct.unpack_from(order + ("Q" if big else "I"), data, 8 if big else 4)
        while at:
            if at in seen:
                raise TiffError("directories in a circle")
            seen.add(at)
            tags, at = _directory(data, at, order, big)
            try:
                pixels, about = _page(data, tags, order, max_bytes)
            except (TiffError, struct.error) as e:
                yield None, {}, str(e)
                continue
            yield pixels, about, None
    except (TiffError, struct.error) as e:
        yield None, {}, str(e)


def write(images: list[np.ndarray], codecs: list[int], predictor: int | dict[int, int] = 2, rows_per_strip: int = 128, tile: tuple[int, int] | list[tuple[int, int] | None] | None = None, order: str = "<") -> bytes:
    """A classic file of 8-bit pages (rows x columns, or rows x columns x samples), one codec a page; ``tile`` (rows, columns)
    for all pages or for each, None: strips; ``predictor`` for LZW and deflate, or by codec."""
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(order + "HI", 42, 0))
    link = 4
    tiles = tile if isinstance(tile, list) else [tile] * len(images)
    for image, codec, tile in zip(images, codecs, tiles, strict=True):
        pixels = image.reshape(image.shape[0], image.shape[1], -1)
        height, width, samples = pixels.shape
        use = predictor.get(codec, 1) if isinstance(predictor, dict) else predictor if codec in (LZW, DEFLATE) else 1
        bh, bw = tile or (min(rows_per_strip, height), width)
        places, counts = [], []
        for y in range(0, height, bh):
            for x in range(0, width, bw):
                block = pixels[y : y + bh, x : x + bw]
                if tile and block.shape[:2] != (bh, bw):
                    whole = np.zeros((bh, bw, samples), np.uint8)
                    whole[: block.shape[0], : block.shape[1]] = block
                    block = whole
                raw = encode((_predict(block) if use == 2 else block).tobytes(), codec)
                places.append(len(out))
                counts.append(len(raw))
                out += raw
        entries = {256: ("I", [width]), 257: ("I", [height]), 258: ("H", [8] * samples), 259: ("H", [codec]), 262: ("H", [2 if samples == 3 else 1]), 277: ("H", [samples]), 284: ("H", [1]), 317: ("H", [use])}
        entries |= {322: ("I", [bw]), 323: ("I", [bh]), 324: ("I", places), 325: ("I", counts)} if tile else {273: ("I", places), 278: ("I", [bh]), 279: ("I", counts)}
        fields = []
        for tag in sorted(entries):
            letter, values = entries[tag]
            raw = struct.pack(f"{order}{len(values)}{letter}", *values)
            if len(raw) > 4:
                raw, at = struct.pack(order + "I", len(out) + len(out) % 2), len(out) + len(out) % 2
                out += b"\0" * (at - len(out)) + struct.pack(f"{order}{len(values)}{letter}", *values)
            fields.append(struct.pack(order + "HHI", tag, 3 if letter == "H" else 4, len(values)) + raw.ljust(4, b"\0"))
        out += b"\0" * (len(out) % 2)
        struct.pack_into(order + "I", out, link, len(out))
        out += struct.pack(order + "H", len(fields)) + b"".join(fields)
        link = len(out)
        out += struct.pack(order + "I", 0)
    return bytes(out)


# ------------------------------------------------------------------ tables


PAGE = {"page": "int", "width": "long", "height": "long", "samples": "int", "bits": "int", "compression": "int", "predictor": "int", "layout": "string", "blocks": "int", "pixels": "binary", "error": "string"}


def explode_pages(df: DataFrame, keep: list[str], data_col: str = "data", max_bytes: int = 1 << 28) -> DataFrame:
    """``keep`` beside PAGE: a row for each page of the files in ``data_col``, pixels row by row in native byte order.

    A null, empty or foreign value gives one row with ``error``, and so does a page that cannot be decoded or would take more than
    ``max_bytes`` (a task's memory cannot spill).  Repeated rows each give their pages; an empty table gives none.  A kept column
    whose name is among PAGE's comes back as ``<name>_in``.
    """
    names = common.free_names(keep, PAGE)
    schema = T.StructType([*(T.StructField(new, df.schema[old].dataType) for old, new in names), *T._parse_datatype_string(", ".join(f"{k} {v}" for k, v in PAGE.items())).fields])
    src = df.select(*[df[c].alias(f"k{i}") for i, (c, _) in enumerate(names)], df[data_col].alias("data"))
    kinds = [f.dataType for f in schema.fields[len(names) :]]

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        rows, take = [], []
        for i, data in enumerate(part.column(len(names)).to_pylist()):
            for k, (pixels, about, error) in enumerate(pages(data, max_bytes)):
                take.append(i)
                rows.append({"page": k, "pixels": None if pixels is None else pixels.tobytes(), "error": error} | about)
        at = pa.array(take, pa.int64())
        from pyspark.sql.pandas.types import to_arrow_type

        made = [pa.array([r.get(c) for r in rows], to_arrow_type(k)) for c, k in zip(PAGE, kinds, strict=True)]
        return pa.RecordBatch.from_arrays([*(part.column(i).take(at) for i in range(len(names))), *made], names=schema.names)

    return common.map_arrow(src, run, schema, "data")


#: A payload is a multiple of so many bytes; a page has so many samples a row and so many rows at most.
UNIT, WIDTH, PAGE_ROWS = 64, 16, 4096
#: Codec and layout of a file's pages in turn: any three that follow each other have every codec and both layouts.
TURNS = [(LZW, False), (PACKBITS, True), (DEFLATE, False), (LZW, True), (PACKBITS, False), (DEFLATE, True)]


def payload(text: bytes) -> bytes:
    """The text and zeros up to a positive multiple of 64 bytes."""
    return text + b"\0" * (-len(text) % UNIT or (0 if text else UNIT))


def store(data: bytes) -> bytes:
    """A payload as three pages or more of 16 samples a row, about equal in size.

    Whatever its length, a file has pages in LZW, PackBits and deflate, in strips and in tiles; its content says with which of
    TURNS it begins.  Deflate pages keep differences of samples, the others the samples themselves: differences of letters repeat less.
    """
    rows = np.frombuffer(data, np.uint8).reshape(-1, WIDTH)
    n = max(3, -(-len(rows) // PAGE_ROWS))
    first = zlib.crc32(data) % len(TURNS)
    edges = [len(rows) * k // n for k in range(n + 1)]
    images = [rows[lo:hi] for lo, hi in zip(edges, edges[1:], strict=False)]
    turns = [TURNS[(first + k) % len(TURNS)] for k in range(n)]
    tiles = [(min(128, -(-len(i) // 16) * 16), WIDTH) if tiled else None for i, (_, tiled) in zip(images, turns, strict=True)]
    return write(images, [c for c, _ in turns], {DEFLATE: 2}, 512, tiles)


def _feature(a: np.ndarray, n: int) -> str:
    seen = np.bincount(a, minlength=256)
    share = seen[seen > 0] / len(a)
    entropy = round(1000 * float(-(share * np.log2(share)).sum()))
    return f"pages={n};sum={int(a.sum(dtype=np.int64))};distinct={int((seen > 0).sum())};entropy={entropy}"


def text_media(df: DataFrame, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """Every text stored as a TIFF file and read back: the digests of op2 and its pages.

    A null text is the empty one; equal texts and repeated rows give equal values, texts of any length are stored whole, an empty
    table gives no rows; kept columns of the same names come back as ``<name>_in``.
    """
    out = {"n_bytes": "long", "payload_bytes": "long", "payload_sha256": "string", "tail_crc32": "long", "media_bytes": "long", "media_sha256": "string", "feature": "string", "n_pages": "long"}

    def run(column: pa.Array) -> dict[str, pa.Array]:
        cols: dict[str, list] = {k: [] for k in out}
        for text in common.text_bytes(column):
            media = store(payload(text))
            got = list(pages(media))
            if any(e for _, _, e in got):
                raise TiffError(next(e for _, _, e in got if e))
            back = np.concatenate([p.ravel() for p, _, _ in got])
            raw = back.tobytes()
            for k, v in zip(out, (len(text), len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), _feature(back, len(got)), len(got)), strict=True):
                cols[k].append(v)
        return {k: pa.array(v, pa.int64() if out[k] == "long" else pa.string()) for k, v in cols.items()}

    return common.annotate(df, run, out, list(keep), text_col)


