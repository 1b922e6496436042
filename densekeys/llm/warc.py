"""WARC derivative builder: metadata and plain-text conversion records from response records.

A response is parsed (record headers, HTTP head, chunked, gzip and deflate bodies, charset), and gives two
records linked to it: a `metadata` record of application/warc-fields, and a `conversion` record of text/plain.
Both carry the response's id in WARC-Refers-To, its target URI, date, payload digest and block digest; the
metadata record repeats every header of the source record and of its HTTP head, as written and in order.

Pages are read once from left to right, so that time grows with their length, whatever they hold. A comment,
script, style, noscript or template without an end is an ordinary tag; a `<` without a `>` after it is text.

Defined cases: a null or empty body gives a conversion of the empty text; a record that can't be parsed, or
whose body inflates beyond MAX_BODY, gives one row of type `error`; a null URL leaves the target URI out;
repeated rows give repeated records, rows of one id and URL with different pages different ids; an empty table
gives an empty result.
"""

from __future__ import annotations

import base64
import codecs
import hashlib
import html
import re
import uuid
import zlib
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VERSION = "WARC/1.1"
DATE = "2000-01-01T00:00:00Z"
MAX_BODY = 1 << 28
#: Fixed: elements whose content isn't shown, and elements that begin a line.
HIDDEN = ("script", "style", "noscript", "template")
BREAKING = frozenset("p div br h1 h2 h3 h4 h5 h6 li ul ol tr table section article header footer nav title blockquote pre hr td th".split())
ENDS = {name: re.compile(rf"</{name}\s*>", re.I) for name in (*HIDDEN, "title")} | {"!--": re.compile("-->")}
OPENING = re.compile(r"<(?:(!--)|(/?)([a-zA-Z][a-zA-Z0-9]*)|[/!?])")
HREF = re.compile(r"\bhref\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
CHUNK_SIZE = re.compile(rb"[0-9A-Fa-f]{1,16}")
#: Fixed: codecs that aren't character sets of pages.
NO_CHARSETS = frozenset(("idna", "punycode", "undefined", "unicode_escape", "raw_unicode_escape"))
#: References to no character, which are too long to read as numbers.
LONG_REFERENCE = re.compile(r"&#(?:[0-9]{9,}|[xX][0-9a-fA-F]{9,});?")
CHARSET = re.compile(r"charset\s*=\s*[\"']?([\w.:-]+)", re.I)


def digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def record(headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = [VERSION, *(f"{k}: {v}" for k, v in headers), f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode("utf-8", "replace") + b"\r\n\r\n" + block + b"\r\n\r\n"


def record_id(*parts: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, ' '.join(map(str, parts)))}>"


def response_of(page_id: int | None, url: str | None, body: str | None) -> bytes:
    """A response record around a page."""
    payload = (body or "").encode("utf-8", "surrogatepass")
    told = digest(payload)
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload
    headers = [("WARC-Type", "response"), ("WARC-Record-ID", record_id("response", page_id, url, told)), ("WARC-Date", DATE)]
    headers += [("WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A"))] if url else []
    headers += [("WARC-Payload-Digest", told), ("WARC-Block-Digest", digest(http)), ("Content-Type", "application/http; msgtype=response")]
    return record(headers, http)


def head_and_rest(data: bytes) -> tuple[str, list[tuple[str, str]], bytes]:
    """First line, headers as written (folded lines joined), and what follows the blank line."""
    end = data.find(b"\r\n\r\n")
    if end < 0:
        raise ValueError("no end of headers")
    first, *lines = data[:end].decode("utf-8", "replace").split("\r\n")
    held: list[tuple[str, list[str]]] = []
    for line in lines:
        if line[:1] in (" ", "\t") and held:
            held[-1][1].append(line.strip())
        elif ":" in line:
            name, value = line.split(":", 1)
            held.append((name.strip(), [value.strip()]))
    return first, [(name, " ".join(values)) for name, values in held], data[end + 4 :]


def by_name(headers: list[tuple[str, str]]) -> dict[str, str]:
    """Lower-cased names to values; of a repeated header the last."""
    return {name.lower(): value for name, value in headers}


def parse_record(data: bytes) -> tuple[list[tuple[str, str]], bytes]:
    first, headers, rest = head_and_rest(data)
    if not first.startswith("WARC/"):
        raise ValueError("not a WARC record")
    size = int(by_name(headers).get("content-length", "-1"))
    if size < 0 or len(rest) < size:
        raise ValueError("the block is shorter than its length")
    return headers, rest[:size]


def dechunked(data: bytes) -> bytes:
    out, at = bytearray(), 0
    while True:
        end = data.index(b"\r\n", at)
        told = data[at:end].split(b";")[0].strip()
        if not CHUNK_SIZE.fullmatch(told):
            raise ValueError("a chunk's size is no number")
        size = int(told, 16)
        if not size:
            return bytes(out)
        if end + 2 + size > len(data):
            raise ValueError("a chunk is longer than the body")
        out += data[end + 2 : end + 2 + size]
        at = end + 4 + size


def inflated(data: bytes, window: int, most: int | None = None) -> bytes:
    """All members of a compressed body, refused where they exceed `most` bytes."""
    most = MAX_BODY if most is None else most
    out = bytearray()
    while data:
        member = zlib.decompressobj(window)
        out += member.decompress(data, most + 1 - len(out))
        if len(out) > most:
            raise ValueError(f"the body inflates to more than {most} bytes")
        if not member.eof:
            raise ValueError("the compressed body ends early")
        data = member.unused_data if window > 15 else b""
    return bytes(out)


def http_body(block: bytes) -> tuple[str, list[tuple[str, str]], bytes]:
    """Status line, headers, and the body with transfer and content coding undone."""
    status, headers, body = head_and_rest(block)
    named = by_name(headers)
    if "chunked" in named.get("transfer-encoding", "").lower():
        body = dechunked(body)
    coding = named.get("content-encoding", "").lower()
    if coding in ("gzip", "x-gzip"):
        body = inflated(body, 31)
    elif coding == "deflate":
        body = inflated(body, 15 if body[:1] and body[0] & 15 == 8 else -15)
    return status, headers, body


def decoded(body: bytes, headers: dict[str, str]) -> tuple[str, str]:
    found = CHARSET.search(headers.get("content-type", "")) or CHARSET.search(body[:1024].decode("latin-1"))
    charset = found.group(1) if found else "utf-8"
    try:
        if codecs.lookup(charset).name in NO_CHARSETS:
            return body.decode("utf-8", "replace"), "utf-8"
        return body.decode(charset, "replace"), charset.lower()
    except LookupError:
        return body.decode("utf-8", "replace"), "utf-8"


def unescaped(text: str) -> str:
    return html.unescape(LONG_REFERENCE.sub("\ufffd", text))


@dataclass
class Page:
    """What a page shows: pieces of text and line breaks, its title as written, and the targets of its links."""

    pieces: list[str]
    title: str | None
    links: list[str]

    @property
    def text(self) -> str:
        """Visible text, a line for each block of the page."""
        lines = (" ".join(line.split()) for line in unescaped("".join(self.pieces)).split("\n"))
        return "\n".join(line for line in lines if line)


def read_page(page: str) -> Page:
    """One scan from left to right. An end that was sought in vain once isn't sought again."""
    out = Page([], None, [])
    unended: set[str] = set()

    def end_of(name: str, start: int) -> re.Match | None:
        found = None if name in unended else ENDS[name].search(page, start)
        if found is None:
            unended.add(name)
        return found

    # no tag ends behind the last `>`, so every opening before it is followed by an end
    at, last, pieces = 0, page.rfind(">") + 1, out.pieces
    while found := OPENING.search(page, at, last):
        left = found.start()
        pieces.append(page[at:left])
        comment, closing, name = found.groups()
        if comment and (end := end_of("!--", found.end())):
            pieces.append(" ")
            at = end.end()
            continue
        right = page.find(">", found.end())
        at = right + 1
        if not name:
            continue
        name = name.lower()
        if name in BREAKING:
            pieces.append("\n")
        if closing:
            continue
        if name == "a":
            if target := HREF.search(page, left, at):
                out.links.append(target[target.lastindex])
        elif name in HIDDEN and (end := end_of(name, at)):
            pieces.append(" ")
            at = end.end()
        elif name == "title" and out.title is None and (end := end_of(name, at)):
            out.title = page[at : end.start()]
    pieces.append(page[at:])
    return out


def one_line(text: str) -> str:
    return " ".join(text.split())


def derive(data: bytes) -> list[dict]:
    """The metadata and conversion records of one response record."""
    headers, block = parse_record(data)
    named = by_name(headers)
    if named.get("warc-type") != "response":
        raise ValueError("not a response record")
    status, http, body = http_body(block)
    text, charset = decoded(body, by_name(http))
    page = read_page(text)
    source, uri = named["warc-record-id"], named.get("warc-target-uri")
    payload, whole = named.get("warc-payload-digest") or digest(body), named.get("warc-block-digest") or digest(block)
    fields = [("source-status", status), ("charset", charset), ("title", one_line(unescaped(page.title or ""))), ("outlinks", str(len(page.links))), ("payload-bytes", str(len(body)))]
    fields += [("source-warc-header", f"{k}: {v}") for k, v in headers] + [("source-http-header", f"{k}: {v}") for k, v in http]
    fields += [("outlink", unescaped(x)) for x in page.links]
    blocks = {"metadata": ("application/warc-fields", "".join(f"{k}: {one_line(v)}\r\n" for k, v in fields)), "conversion": ("text/plain; charset=utf-8", page.text)}
    out = []
    for kind, (content_type, content) in blocks.items():
        raw = content.encode("utf-8", "replace")
        told = digest(raw)
        own = [("WARC-Type", kind), ("WARC-Record-ID", record_id(kind, source)), ("WARC-Refers-To", source), ("WARC-Date", named.get("warc-date", DATE))]
        own += [("WARC-Target-URI", uri)] if uri else []
        own += [("WARC-Block-Digest", told), ("WARC-Source-Payload-Digest", payload), ("WARC-Source-Block-Digest", whole), ("Content-Type", content_type)]
        row = {"record_type": kind, "record_id": own[1][1], "refers_to": source, "target_uri": uri, "block_digest": told, "source_digest": payload, "source_block_digest": whole}
        out.append(row | {"n_links": len(page.links), "content": raw.decode("utf-8"), "record": record(own, raw)})
    return out


FIELDS = {"record_type": pa.string(), "record_id": pa.string(), "refers_to": pa.string(), "target_uri": pa.string(), "block_digest": pa.string(), "source_digest": pa.string(), "source_block_digest": pa.string(), "n_links": pa.int64(), "content": pa.string(), "record": pa.binary(), "error": pa.string()}
SCHEMA = "page_id long, " + ", ".join(f"{k} {'long' if t == pa.int64() else t}" for k, t in FIELDS.items())


def derivatives(rows, build) -> pa.RecordBatch:
    ids, out = [], []
    for page_id, *given in rows:
        try:
            found = derive(build(page_id, *given))
        except (ValueError, KeyError, MemoryError, zlib.error) as e:
            found = [{"record_type": "error", "error": f"{type(e).__name__}: {e}"}]
        ids += [page_id] * len(found)
        out += found
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *(pa.array([r.get(k) for r in out], t) for k, t in FIELDS.items())], ["page_id", *FIELDS])


def derive_records(responses: DataFrame, id_col: str = "page_id", record_col: str = "record") -> DataFrame:
    """Derivatives of a table of response records."""

    def run(batches):
        for batch in batches:
            yield derivatives(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True), lambda _, data: data or b"")

    return responses.select(F.col(f"`{id_col}`").cast("long"), F.col(f"`{record_col}`").cast("binary")).mapInArrow(run, SCHEMA)


def derive_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """A response record for each page, and its derivatives."""

    def run(batches):
        for batch in batches:
            yield derivatives(zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True), response_of)

    columns = [F.col(f"`{c}`").cast(t).alias(n) for c, t, n in ((id_col, "long", "page_id"), (url_col, "string", "url"), (html_col, "string", "html"))]
    return pages.select(*columns).mapInArrow(run, SCHEMA)
