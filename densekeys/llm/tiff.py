"""Media columns: a TIFF writer and reader, one row per page.

The reader walks the chain of image directories, finds the strips or tiles of each, decodes none, PackBits,
LZW or deflate data, undoes horizontal differencing (predictor 2, of 8, 16 or 32 bits) or the floating-point
predictor (3), joins separate sample planes and puts tiles together, in either byte order. The writer makes files
of 8-bit samples, so that any bytes can be stored and read back; which scheme, predictor and layout a payload
takes is told by its checksum, so that all of them are used at every size.

A page larger than MAX_PAGE bytes, or whose blocks hold less than its directory claims, is an error; nothing is
inflated beyond what the directory asks for. Defined cases: a null or empty payload becomes one row of padding;
a broken file gives the pages before the break and one row with page -1 whose `error` is set and whose samples
are null; repeated rows are decoded each; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.llm.common import id_and_text, text_bytes

# Fixed values of the format: tags, compression schemes, sizes of field types.
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC, STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_COUNTS = 256, 257, 258, 259, 262, 273, 277, 278, 279
PLANAR, PREDICTOR, TILE_WIDTH, TILE_HEIGHT, TILE_OFFSETS, TILE_COUNTS, SAMPLE_FORMAT = 284, 317, 322, 323, 324, 325, 339
NONE, LZW, DEFLATE, DEFLATE_OLD, PACKBITS = 1, 5, 8, 32946, 32773
TYPE_SIZE = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8}
CLEAR, END = 256, 257
MAX_PAGE = 1 << 28
SCHEMES = {"none": NONE, "lzw": LZW, "deflate": DEFLATE, "packbits": PACKBITS}


def packbits_encode(data: bytes) -> bytes:
    """Runs of three or more become a repeat, the rest literals of up to 128 bytes."""
    out, n, start = bytearray(), len(data), 0
    values = np.frombuffer(data, np.uint8)
    bounds = np.concatenate([[0], np.flatnonzero(values[1:] != values[:-1]) + 1, [n]]) if n else np.zeros(1, int)
    long = np.diff(bounds) >= 3

    def literal(a: int, b: int) -> None:
        for x in range(a, b, 128):
            part = data[x : min(b, x + 128)]
            out.append(len(part) - 1)
            out.extend(part)

    for i, j in zip(bounds[:-1][long].tolist(), bounds[1:][long].tolist(), strict=True):
        literal(start, i)
        for x in range(i, j, 128):
            k = min(128, j - x)
            out.extend((257 - k, data[i]) if k > 1 else (0, data[i]))
        start = j
    literal(start, n)
    return bytes(out)


def packbits_decode(data: bytes, limit: int) -> bytes:
    out, i = bytearray(), 0
    while i < len(data) and len(out) < limit:
        head = data[i]
        if head < 128:
            out += data[i + 1 : i + 2 + head]
            i += 2 + head
        elif head > 128:
            out += data[i + 1 : i + 2] * (257 - head)
            i += 2
        else:
            i += 1
    return bytes(out)


def code_widths(index: np.ndarray) -> np.ndarray:
    """Bits of the codes that follow a clear code, by their place: 9, and one more from when the table could overflow them, up to 12."""
    return 9 + (index >= 254) + (index >= 766) + (index >= 1790)


def lzw_encode(data: bytes) -> bytes:
    """Codes of 9 to 12 bits, most significant bit first, widened one code early."""
    codes, table, top = [CLEAR], {}, END + 1
    append, held = codes.append, -1
    for byte in data:
        if held < 0:
            held = byte
            continue
        key = held << 8 | byte
        code = table.get(key)
        if code is not None:
            held = code
            continue
        append(held)
        table[key] = top
        top += 1
        held = byte
        if top == 4094:
            append(CLEAR)
            table.clear()
            top = END + 1
    if held >= 0:
        append(held)
    append(END)
    values = np.array(codes, np.uint16)
    place = np.arange(len(values))
    cleared = np.maximum.accumulate(np.where(values == CLEAR, place, 0))
    before = np.concatenate([[-1], cleared[:-1]])  # a clear code is still as wide as the codes it ends
    width = code_widths(place - before - 1)
    bits = np.unpackbits(values.astype(">u2").view(np.uint8)).reshape(-1, 16)
    return np.packbits(bits[np.arange(16) >= 16 - width[:, None]]).tobytes()


def lzw_decode(data: bytes, limit: int) -> bytes:
    """What the codes stand for, at least `limit` bytes if there are so many; a code's string is found in the output, where it first arose."""
    raw = np.frombuffer(data + b"\0\0\0", np.uint8).astype(np.uint32)
    out, starts, at, end = bytearray(), [], 0, 8 * len(data)
    while len(out) < limit:
        width = code_widths(np.arange(len(starts), len(starts) + 1024))
        offset = at + np.cumsum(width) - width
        width, offset = width[offset + width <= end], offset[offset + width <= end]
        if not len(width):
            break
        word = raw[offset >> 3] << 16 | raw[(offset >> 3) + 1] << 8 | raw[(offset >> 3) + 2]
        codes = word >> (24 - (offset & 7) - width).astype(np.uint32) & ((1 << width) - 1).astype(np.uint32)
        stop = np.flatnonzero((codes == CLEAR) | (codes == END))
        used = int(stop[0]) if len(stop) else len(codes)
        at = int(offset[used] + width[used]) if len(stop) else int(offset[-1] + width[-1])
        for code in codes[:used].tolist():
            starts.append(len(out))
            if code < CLEAR:
                out.append(code)
                continue
            begin = starts[code - END - 1]
            upto = starts[code - END] + 1
            piece = out[begin:upto]
            # the last byte of the newest string is its own first
            out += piece if len(piece) == upto - begin else piece + piece[:1]
        if len(stop):
            if codes[used] == END:
                break
            starts = []
    return bytes(out)


def pack(data: bytes, scheme: int, level: int = 1) -> bytes:
    if scheme == PACKBITS:
        return packbits_encode(data)
    if scheme == LZW:
        return lzw_encode(data)
    return zlib.compress(data, level) if scheme == DEFLATE else data


def unpack(data: bytes, scheme: int, size: int) -> bytes:
    if scheme == PACKBITS:
        out = packbits_decode(data, size)
    elif scheme == LZW:
        out = lzw_decode(data, size)
    elif scheme in (DEFLATE, DEFLATE_OLD):
        out = zlib.decompressobj().decompress(data, size) if size else b""
    elif scheme == NONE:
        out = data
    else:
        raise ValueError(f"compression {scheme} is not supported")
    if len(out) < size:
        raise ValueError(f"a block holds {len(out)} of {size} bytes")
    return out[:size]


def write_tiff(pages: list[np.ndarray], compression: str = "deflate", predictor: int = 1, rows_per_strip: int = 256, tile: tuple[int, int] | None = None) -> bytes:
    """Pages of shape (height, width, samples), 8 bits each, as one little-endian file of strips or tiles."""
    scheme = SCHEMES[compression]
    out = bytearray(b"II*\0\0\0\0\0")
    link = 4
    for page in pages:
        height, width, samples = page.shape
        blocks = []
        if tile:
            tw, th = tile
            full = np.zeros((-(-height // th) * th, -(-width // tw) * tw, samples), np.uint8)
            full[:height, :width] = page
            parts = [full[y : y + th, x : x + tw] for y in range(0, full.shape[0], th) for x in range(0, full.shape[1], tw)]
        else:
            parts = [page[y : y + rows_per_strip] for y in range(0, height, rows_per_strip)]
        for part in parts:
            if predictor == 2:
                part = np.concatenate([part[:, :1], np.diff(part, axis=1)], axis=1)
            data = pack(np.ascontiguousarray(part).tobytes(), scheme)
            blocks.append((len(out), len(data)))
            out += data + b"\0" * (len(data) & 1)
        fields = [(WIDTH, [width]), (HEIGHT, [height]), (BITS, [8] * samples), (COMPRESSION, [scheme]), (PHOTOMETRIC, [2 if samples >= 3 else 1])]
        fields += [(SAMPLES, [samples]), (PLANAR, [1]), (PREDICTOR, [predictor])]
        if tile:
            fields += [(TILE_WIDTH, [tile[0]]), (TILE_HEIGHT, [tile[1]]), (TILE_OFFSETS, [b[0] for b in blocks]), (TILE_COUNTS, [b[1] for b in blocks])]
        else:
            fields += [(ROWS_PER_STRIP, [rows_per_strip]), (STRIP_OFFSETS, [b[0] for b in blocks]), (STRIP_COUNTS, [b[1] for b in blocks])]
        entries = b""
        for tag, values in sorted(fields):
            long = tag in (WIDTH, HEIGHT, ROWS_PER_STRIP, STRIP_OFFSETS, STRIP_COUNTS, TILE_WIDTH, TILE_HEIGHT, TILE_OFFSETS, TILE_COUNTS)
            data = struct.pack(f"<{len(values)}{'I' if long else 'H'}", *values)
            if len(data) > 4:
                at = len(out)
                out += data + b"\0" * (len(data) & 1)
                data = struct.pack("<I", at)
            entries += struct.pack("<HHI", tag, 4 if long else 3, len(values)) + data.ljust(4, b"\0")
        struct.pack_into("<I", out, link, len(out))
        out += struct.pack("<H", len(fields)) + entries
        link = len(out)
        out += b"\0\0\0\0"
    return bytes(out)


def directories(data: bytes):
    """Fields of each image directory in the order of the chain; a loop in the chain is an error."""
    if data[:2] not in (b"II", b"MM"):
        raise ValueError("no TIFF header")
    e = byte_order(data)
    if struct.unpack_from(e + "H", data, 2)[0] != 42:
        raise ValueError("no TIFF header")
    (at,) = struct.unpack_from(e + "I", data, 4)
    seen = set()
    while at:
        if at in seen:
            raise ValueError("the directories form a loop")
        seen.add(at)
        (n,) = struct.unpack_from(e + "H", data, at)
        fields = {}
        for k in range(n):
            tag, kind, count = struct.unpack_from(e + "HHI", data, at + 2 + 12 * k)
            size = TYPE_SIZE.get(kind, 1) * count
            where = at + 10 + 12 * k if size <= 4 else struct.unpack_from(e + "I", data, at + 10 + 12 * k)[0]
            if kind in (1, 3, 4):
                fields[tag] = list(struct.unpack_from(f"{e}{count}{ {1: 'B', 3: 'H', 4: 'I'}[kind] }", data, where))
        yield fields
        (at,) = struct.unpack_from(e + "I", data, at + 2 + 12 * n)


def sample_type(fields: dict[int, list[int]], order: str) -> np.dtype:
    bits, form = set(fields.get(BITS, [1])), set(fields.get(SAMPLE_FORMAT, [1]))
    if len(bits) != 1 or len(form) != 1 or not bits <= {8, 16, 32} or not form <= {1, 2, 3, 4} or form == {3} and bits != {32}:
        raise ValueError(f"samples of {sorted(bits)} bits and form {sorted(form)} are not supported")
    # differences wrap alike in signed and unsigned samples, so their bytes are all that matters
    return np.dtype(f"{order}{'f' if form == {3} else 'u'}{bits.pop() // 8}")


def undone(part: np.ndarray, predictor: int, kind: np.dtype) -> np.ndarray:
    """Samples of a block of shape (rows, columns, samples), given as raw bytes of shape (rows, bytes of a row)."""
    h, samples = part.shape[0], part.shape[2]
    if predictor == 3:
        # byte planes, most significant first, differenced along the row
        planes = np.cumsum(part.reshape(h, -1, samples), axis=1, dtype=np.uint8).reshape(h, kind.itemsize, -1)
        return np.ascontiguousarray(planes.transpose(0, 2, 1)).view(kind.newbyteorder(">")).reshape(h, -1, samples)
    values = part.reshape(h, -1).view(kind).reshape(h, -1, samples)
    if predictor == 2:
        whole = np.dtype(f"u{kind.itemsize}")
        return np.cumsum(values.astype(kind.newbyteorder("=")).view(whole), axis=1, dtype=whole).view(kind.newbyteorder("="))
    return values


def read_page(data: bytes, fields: dict[int, list[int]], order: str = "<") -> np.ndarray:
    """Samples of shape (height, width, samples), in the machine's byte order."""
    width, height, samples = fields[WIDTH][0], fields[HEIGHT][0], fields.get(SAMPLES, [1])[0]
    kind = sample_type(fields, order)
    scheme, predictor, planar = fields.get(COMPRESSION, [NONE])[0], fields.get(PREDICTOR, [1])[0], fields.get(PLANAR, [1])[0]
    if predictor not in (1, 2, 3) or (predictor == 3) != (kind.kind == "f") and predictor != 1:
        raise ValueError(f"predictor {predictor} is not supported for these samples")
    if planar not in (1, 2):
        raise ValueError(f"planar configuration {planar}")
    tiled = TILE_OFFSETS in fields
    w, h = (fields[TILE_WIDTH][0], fields[TILE_HEIGHT][0]) if tiled else (width, min(height, fields.get(ROWS_PER_STRIP, [height])[0]))
    if min(width, height, samples, w, h) < 1:
        raise ValueError("a size is zero")
    across, down = -(-width // w), -(-height // h)
    planes, together = (samples, 1) if planar == 2 else (1, samples)
    if across * w * (down * h if tiled else height) * samples * kind.itemsize > MAX_PAGE:
        raise ValueError(f"a page of {width} by {height} by {samples} samples is larger than {MAX_PAGE} bytes")
    starts, sizes = (fields[TILE_OFFSETS], fields[TILE_COUNTS]) if tiled else (fields[STRIP_OFFSETS], fields[STRIP_COUNTS])
    if len(starts) != len(sizes) or len(starts) != across * down * planes:
        raise ValueError(f"{len(starts)} blocks, not {across * down * planes}")
    full = np.zeros((down * h if tiled else height, across * w, samples), kind.newbyteorder("="))
    for k, (at, size) in enumerate(zip(starts, sizes, strict=True)):
        plane, place = divmod(k, across * down)
        y, x = place // across * h, place % across * w
        rows = h if tiled else min(h, height - y)
        raw = np.frombuffer(unpack(data[at : at + size], scheme, rows * w * together * kind.itemsize), np.uint8)
        block = undone(raw.reshape(rows, -1, together), predictor, kind)
        full[y : y + rows, x : x + w, plane : plane + together] = block
    return full[:height, :width]


def byte_order(data: bytes) -> str:
    return ">" if data[:2] == b"MM" else "<"


def read_tiff(data: bytes) -> list[np.ndarray]:
    return [read_page(data, fields, byte_order(data)) for fields in directories(data)]


PAGE_SCHEMA = "media_id long, page int, width int, height int, samples int, bits int, compression int, tiled boolean, data binary, error string"


def explode_pages(media: DataFrame, id_col: str = "media_id", data_col: str = "data") -> DataFrame:
    """One row per page of every TIFF; a file that can't be read is one row with page -1 and its error."""

    def walk(batches):
        for batch in batches:
            rows = []
            for media_id, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                try:
                    for k, fields in enumerate(directories(data or b"")):
                        page = read_page(data, fields, byte_order(data))
                        rows.append((media_id, k, page.shape[1], page.shape[0], page.shape[2], 8 * page.itemsize, fields.get(COMPRESSION, [NONE])[0], TILE_OFFSETS in fields, page.tobytes(), None))
                except (ValueError, KeyError, IndexError, ArithmeticError, MemoryError, struct.error, zlib.error) as e:
                    rows.append((media_id, -1, None, None, None, None, None, None, None, f"{type(e).__name__}: {e}"))
            kinds = (pa.int64(), *[pa.int32()] * 6, pa.bool_(), pa.binary(), pa.string())
            names = [x.split()[0] for x in PAGE_SCHEMA.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [[]] * len(kinds), kinds, strict=True)], names)

    return media.select(F.col(f"`{id_col}`").cast("long"), F.col(f"`{data_col}`").cast("binary")).mapInArrow(walk, PAGE_SCHEMA)


ROW_BYTES, ROWS_PER_PAGE = 192, 512


#: What the writer makes, by the payload's checksum: scheme, predictor, rows of a strip, tile.
FORMS = (
    ("deflate", 2, 64, None),
    ("deflate", 2, 0, (32, 16)),
    ("packbits", 1, 64, None),
    ("packbits", 2, 0, (16, 16)),
    ("lzw", 2, 128, None),
    ("lzw", 1, 0, (64, 16)),
    ("none", 1, 512, None),
    ("none", 2, 0, (32, 32)),
)


def store_payload(payload: bytes) -> bytes:
    """Rows of 64 pixels of three samples, a page for every 512 rows, in the form that the payload's checksum picks; equal texts have equal stored forms."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, 64, 3)
    pages = [rows[k : k + ROWS_PER_PAGE] for k in range(0, len(rows), ROWS_PER_PAGE)]
    scheme, predictor, strip, tile = FORMS[zlib.crc32(payload) % len(FORMS)]
    return write_tiff(pages, scheme, predictor, strip, tile)


def features(pages: list[np.ndarray]) -> str:
    """Pages, rows, and the mean and spread of the samples that were read back."""
    n = sum(p.size for p in pages)
    total = sum(int(p.sum(dtype=np.int64)) for p in pages)
    bins = sum(np.bincount(p.reshape(-1) >> 5, minlength=8) for p in pages)
    return f"pages={len(pages)};rows={sum(len(p) for p in pages)};mean={total / n:.4f};bins={','.join(map(str, bins.tolist()))}"


def text_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store every whole text as a TIFF, read the stored bytes back and describe both."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_pages int"
    names = [x.split()[0] for x in schema.split(", ")]
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32())

    def roundtrip(batches):
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), text_bytes(batch.column(1)), strict=True):
                media = store_payload(text + b" " * (ROW_BYTES - len(text) if not text else -len(text) % ROW_BYTES))
                pages = read_tiff(media)
                back = b"".join(p.tobytes() for p in pages)
                rows.append((doc_id, len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-16:]), len(media), hashlib.sha256(media).hexdigest(), features(pages), len(pages)))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [[]] * len(kinds), kinds, strict=True)], names)

    return id_and_text(docs, id_col, text_col).mapInArrow(roundtrip, schema)
