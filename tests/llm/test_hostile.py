"""Inputs made to hang, blow up or crash a reader: each ends soon, with a defined result."""

from __future__ import annotations

import gzip
import hashlib
import random
import resource
import struct
import time
import zlib

import numpy as np
import pytest

from densekeys.llm import tiff, warc


def response(http: bytes) -> bytes:
    return warc.record([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:uuid:1>")], http)


# --- WARC


@pytest.mark.parametrize("page", ["<!--" * 250_000, "<script " * 125_000, "<a " * 330_000, "<title>" * 140_000, "<" * 1_000_000, "<!-- >" * 170_000, "<script>" * 125_000, "<script>" + "</script " * 110_000, "<a href='" * 110_000, "&#" + "9" * 1_000_000])
def test_a_megabyte_of_openings_is_read_at_once(page):
    began = time.perf_counter()
    rows = warc.derive(warc.response_of(1, "http://a/b", page))
    assert [r["record_type"] for r in rows] == ["metadata", "conversion"] and time.perf_counter() - began < 3


@pytest.mark.parametrize("size", [b"-6", b"+6", b"1_0", b"zz", b"", b"7fffffffffffffff"])
def test_chunks_of_no_size_are_refused(size):
    with pytest.raises(ValueError):
        warc.dechunked(size + b"\r\nabcdef\r\n0\r\n\r\n")
    assert warc.derivatives([(1, b"")], lambda *_: response(b"HTTP/1.1 200 OK\r\nTransfer-Encoding: chunked\r\n\r\n" + size + b"\r\nabc"))["record_type"].to_pylist() == ["error"]


@pytest.mark.parametrize("window", [31, 15, -15])
def test_bodies_inflate_no_further_than_allowed(window):
    packer = zlib.compressobj(9, zlib.DEFLATED, window)
    bomb = packer.compress(bytes(20_000_000)) + packer.flush()
    assert len(warc.inflated(bomb, window, 20_000_000)) == 20_000_000
    with pytest.raises(ValueError, match="inflates"):
        warc.inflated(bomb, window, 1_000_000)
    with pytest.raises(ValueError, match="early"):
        warc.inflated(bomb[:-50], window)
    assert warc.inflated(gzip.compress(b"a") + gzip.compress(b"b"), 31) == b"ab"


def test_odd_charsets_and_references():
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=punycode\r\n\r\n<p>a&#99999999999999;b &lt; c</p><!-- open"
    assert warc.derive(response(http))[1]["content"] == "a�b < c\n<!-- open"
    assert warc.derive(response(b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=nonesuch\r\n\r\n1 < 2 <br> 3"))[1]["content"] == "1 < 2\n3"


def test_every_source_header_is_kept_in_order():
    http = b"HTTP/1.1 200 OK\r\nSet-Cookie: a=1\r\nX-Long: one\r\n two\r\nSet-Cookie: b=2\r\n\r\nx"
    source = warc.record([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:uuid:1>"), ("WARC-Block-Digest", "sha1:B"), ("WARC-Payload-Digest", "sha1:P"), ("WARC-IP-Address", "1.2.3.4")], http)
    meta, text = warc.derive(source)
    lines = meta["content"].split("\r\n")
    assert [x.split(": ", 1)[1] for x in lines if x.startswith("source-http-header")] == ["Set-Cookie: a=1", "X-Long: one two", "Set-Cookie: b=2"]
    assert "source-warc-header: WARC-IP-Address: 1.2.3.4" in lines
    for row in (meta, text):
        headers = warc.by_name(warc.parse_record(row["record"])[0])
        assert (headers["warc-source-payload-digest"], headers["warc-source-block-digest"], headers["warc-refers-to"]) == ("sha1:P", "sha1:B", "<urn:uuid:1>")


def test_different_pages_of_one_address_have_different_records():
    ids = {warc.derive(warc.response_of(None, None, p))[0]["record_id"] for p in ("a", "b", "b")}
    assert len(ids) == 2


# --- TIFF


def entry(tag: int, kind: int, count: int, value: bytes, order: str) -> bytes:
    return struct.pack(order + "HHI", tag, kind, count) + value


def foreign(order: str, width: int, height: int, blocks: list[bytes], extra: dict[int, list[int]], bits: int = 8, samples: int = 1, tile: tuple[int, int] | None = None) -> bytes:
    """A file put together by hand, its directory before its data and every number as a LONG."""
    tags = {256: [width], 257: [height], 258: [bits] * samples, 277: [samples], **extra}
    offsets, counts = (324, 325) if tile else (273, 279)
    tags |= {322: [tile[0]], 323: [tile[1]]} if tile else {}
    tags |= {offsets: [0] * len(blocks), counts: [len(b) for b in blocks]}
    head = 8 + 2 + 12 * len(tags) + 4
    lists = head + sum(4 * len(v) for v in tags.values() if len(v) > 1)
    at = lists
    for k, b in enumerate(blocks):
        tags[offsets][k] = at
        at += len(b)
    out, spare, place = b"", b"", head
    for tag, values in sorted(tags.items()):
        raw = struct.pack(f"{order}{len(values)}I", *values)
        if len(values) > 1:
            spare += raw
            raw, place = struct.pack(order + "I", place), place + len(raw)
        out += entry(tag, 4, len(values), raw, order)
    mark = b"II*\0" if order == "<" else b"MM\0*"
    return mark + struct.pack(order + "IH", 8, len(tags)) + out + b"\0\0\0\0" + spare + b"".join(blocks)


def test_published_examples_of_the_codecs():
    """The worked examples of the format's description, made by no code of ours."""
    packed = bytes.fromhex("FEAA0280002AFDAA0380002A22F7AA")
    plain = bytes.fromhex("AAAAAA80002AAAAAAAAA80002A22" + "AA" * 10)
    assert tiff.packbits_decode(packed, len(plain)) == plain
    codes = [256, 7, 258, 8, 8, 258, 6, 6, 257]
    bits = "".join(f"{c:09b}" for c in codes)
    data = int(bits.ljust(-(-len(bits) // 8) * 8, "0"), 2).to_bytes(-(-len(bits) // 8), "big")
    assert tiff.lzw_decode(data, 10) == bytes([7, 7, 7, 8, 8, 7, 7, 6, 6]) and tiff.lzw_encode(bytes([7, 7, 7, 8, 8, 7, 7, 6, 6])) == data


@pytest.mark.parametrize("order", "<>")
def test_foreign_files(order):
    wide = (np.arange(6).reshape(2, 3) * 1000).astype(f"{order}u2")
    (page,) = tiff.read_tiff(foreign(order, 3, 2, [wide.tobytes()], {}, 16))
    assert page[:, :, 0].tolist() == wide.tolist()
    differences = np.diff(wide.astype("u2"), axis=1, prepend=np.zeros((2, 1), "u2")).astype(f"{order}u2")
    (page,) = tiff.read_tiff(foreign(order, 3, 2, [zlib.compress(differences.tobytes())], {259: [8], 317: [2]}, 16))
    assert page[:, :, 0].tolist() == wide.tolist()
    planes = [bytes([1, 2, 3, 4]), bytes([5, 6, 7, 8]), bytes([9, 10, 11, 12])]
    (page,) = tiff.read_tiff(foreign(order, 2, 2, planes, {284: [2]}, 8, 3))
    assert page.tolist() == [[[1, 5, 9], [2, 6, 10]], [[3, 7, 11], [4, 8, 12]]]
    floats = np.array([[1.5, -2.25, 1e10, 0.0]], ">f4")
    raw = np.ascontiguousarray(floats.view(np.uint8).reshape(1, 4, 4).transpose(0, 2, 1)).reshape(1, 16)
    coded = np.diff(raw, axis=1, prepend=np.zeros((1, 1), np.uint8)).tobytes()
    (page,) = tiff.read_tiff(foreign(order, 4, 1, [tiff.packbits_encode(coded)], {259: [32773], 317: [3], 339: [3]}, 32))
    assert page[0, :, 0].tolist() == floats[0].tolist()


@pytest.mark.parametrize("tags", [{322: [0]}, {323: [0]}, {256: [0]}, {277: [0]}, {256: [1 << 31], 257: [1 << 31]}, {322: [1 << 30], 323: [1 << 30]}, {258: [12]}, {317: [9]}, {284: [7]}, {339: [9]}, {325: [4, 4]}])
def test_claims_of_a_directory_are_checked(spark, tags):
    data = foreign("<", 2, 2, [b"abcd"], {}, tile=(2, 2))
    for tag, values in tags.items():
        at = next((k for k in range(10, len(data) - 12, 12) if struct.unpack_from("<H", data, k)[0] == tag), None)
        if at is None:
            data = foreign("<", 2, 2, [b"abcd"], {tag: values}, tile=(2, 2))
        else:
            data = data[:at] + entry(tag, 4, len(values), struct.pack("<I", values[0]), "<") + data[at + 12 :]
    rows = tiff.explode_pages(spark.createDataFrame([(1, data)], "media_id long, data binary")).collect()
    assert len(rows) == 1 and rows[0]["error"] and rows[0]["page"] == -1


def test_blocks_inflate_no_further_than_their_size():
    data = foreign("<", 10, 10, [zlib.compress(bytes(200_000_000), 9)], {259: [8]})
    began, peak = time.perf_counter(), resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
    assert tiff.read_tiff(data)[0].sum() == 0
    assert time.perf_counter() - began < 1 and resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - peak < 50_000


def test_every_form_is_used_and_described_as_its_payload_is(spark):
    """The columns of the query beside what the payload itself says, for payloads of one size, and of several pages."""
    rng = random.Random(3)
    texts = ["".join(rng.choice("abc def") for _ in range(150)) for _ in range(80)] + ["".join(rng.choice("ab\n é") for _ in range(n)) for n in (70_000, 130_000, 260_000)]
    rows = tiff.text_media(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    used = set()
    for r in rows:
        raw = texts[r["doc_id"]].encode()
        payload = raw + b" " * (-len(raw) % 192)
        used.add(zlib.crc32(payload) % len(tiff.FORMS))
        lines = len(payload) // 192
        bins = [sum(1 for x in payload if x >> 5 == k) for k in range(8)] if lines < 5 else None
        want = f"pages={-(-lines // 512)};rows={lines};mean={sum(payload) / len(payload):.4f};bins="
        assert r["feature"].startswith(want) and (bins is None or r["feature"] == want + ",".join(map(str, bins)))
        media = tiff.store_payload(payload)
        assert (r["media_bytes"], r["media_sha256"], r["n_pages"]) == (len(media), hashlib.sha256(media).hexdigest(), -(-lines // 512))
        pages = [f for f in tiff.directories(media)]
        assert sum(f[257][0] for f in pages) == lines and all(f[256][0] == 64 for f in pages)
    assert used == set(range(len(tiff.FORMS)))
