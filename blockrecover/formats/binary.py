"""Encoders and validators of real file formats: PNG, GIF, ELF, MP3, ZIP and office documents in ZIP.

An encoder wraps (number, data) so that a recovered file gives both back. A validator reads a prefix of a file, as far as it
has been gathered, and says up to which byte it is consistent, whether a complete file has been seen, and whether
more bytes could change that. Bytes behind a complete file do not matter.

Defined results: empty input is not promising; truncated or damaged input never raises; an empty text is a file like any
other; validators read whole files.
"""

from __future__ import annotations

import io
import struct
import zipfile
import zlib
from collections.abc import Callable
from dataclasses import dataclass


@dataclass(frozen=True)
class Verdict:
    """good: bytes consistent from the start; whole: a complete file of ``good`` bytes; more: what is missing may follow."""

    good: int = 0
    whole: bool = False
    more: bool = False
    label: str = ""


@dataclass(frozen=True)
class Format:
    name: str
    signature: bytes
    encode: Callable[[int, bytes], bytes]
    check: Callable[[bytes], Verdict]
    decode: Callable[[bytes], bytes]  # the wrapped bytes of a complete file


def wrap(number: int, data: bytes) -> bytes:
    return struct.pack(">qI", number, len(data)) + data


def unwrap(body: bytes) -> tuple[int, bytes]:
    number, n = struct.unpack_from(">qI", body)
    return number, body[12 : 12 + n]


# ---------------------------------------------------------------- PNG

PNG = b"\x89PNG\r\n\x1a\n"
PNG_WIDTH, PNG_PART = 64, 4096
#: Samples per pixel by colour type and the bit depths each allows (fixed values of the format).
PNG_KINDS = {0: (1, {1, 2, 4, 8, 16}), 2: (3, {8, 16}), 3: (1, {1, 2, 4, 8}), 4: (2, {8, 16}), 6: (4, {8, 16})}


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def png_encode(number: int, data: bytes) -> bytes:
    body = wrap(number, data)
    rows = -(-len(body) // PNG_WIDTH)
    body = body.ljust(rows * PNG_WIDTH, b"\0")
    packed = zlib.compress(b"".join(b"\0" + body[i * PNG_WIDTH : (i + 1) * PNG_WIDTH] for i in range(rows)), 6)
    parts = [_chunk(b"IDAT", packed[i : i + PNG_PART]) for i in range(0, len(packed), PNG_PART)]
    return PNG + _chunk(b"IHDR", struct.pack(">IIBBBBB", PNG_WIDTH, rows, 8, 0, 0, 0, 0)) + _chunk(b"tEXt", b"Title\0%d" % number) + b"".join(parts) + _chunk(b"IEND", b"")


def png_chunks(data: bytes):
    """Yields (kind, start of the data, length) of chunks that are there whole and whose checksums hold."""
    at = len(PNG)
    while at + 12 <= len(data):
        (n,) = struct.unpack_from(">I", data, at)
        kind = data[at + 4 : at + 8]
        if n >> 31 or not kind.isalpha() or at + 12 + n > len(data) or struct.unpack_from(">I", data, at + 8 + n)[0] != zlib.crc32(memoryview(data)[at + 4 : at + 8 + n]):
            return
        yield kind, at + 8, n
        at += 12 + n


def png_check(data: bytes) -> Verdict:
    if not data.startswith(PNG):
        return Verdict()
    good, wanted, got, filters, inflate, seen, closed = len(PNG), None, 0, True, zlib.decompressobj(), set(), False
    stride = 0
    for kind, at, n in png_chunks(data):
        if (kind == b"IHDR") != (not seen) or kind == b"IDAT" and closed:
            return Verdict(good)
        if kind == b"IHDR":
            if n != 13:
                return Verdict(good)
            width, height, depth, colour, method, filter_, lace = struct.unpack_from(">IIBBBBB", data, at)
            if not width or not height or colour not in PNG_KINDS or depth not in PNG_KINDS[colour][1] or method or filter_ or lace > 1:
                return Verdict(good)
            stride = 1 + (width * depth * PNG_KINDS[colour][0] + 7) // 8
            wanted = stride * height if not lace else None
        elif kind == b"IDAT":
            try:
                raw = inflate.decompress(data[at : at + n])
            except zlib.error:
                return Verdict(good)
            if wanted is not None:  # each row begins with the number of its filter
                first = -got % stride
                filters &= all(raw[i] <= 4 for i in range(first, len(raw), stride))
                got += len(raw)
                if not filters or got > wanted:
                    return Verdict(good)
        elif kind == b"IEND":
            whole = n == 0 and inflate.eof and (wanted is None or got == wanted)
            return Verdict(at + 4 if whole else good, whole)
        elif b"IDAT" in seen:
            closed = True
        seen.add(kind)
        good = at + n + 4
    # the next chunk is cut off rather than wrong if its length reaches beyond what is here
    (n,) = struct.unpack_from(">I", data, good) if good + 4 <= len(data) else (0,)
    return Verdict(good, more=good + 12 + n > len(data) and not n >> 31)


def png_decode(data: bytes) -> bytes:
    raw = zlib.decompress(b"".join(data[at : at + n] for kind, at, n in png_chunks(data) if kind == b"IDAT"))
    return b"".join(raw[i + 1 : i + 1 + PNG_WIDTH] for i in range(0, len(raw), PNG_WIDTH + 1))


# ---------------------------------------------------------------- GIF

GIF = b"GIF89a"


class _Bits:
    def __init__(self):
        self.out, self.held, self.n = bytearray(), 0, 0

    def put(self, code: int, width: int) -> None:
        self.held |= code << self.n
        self.n += width
        while self.n >= 8:
            self.out.append(self.held & 255)
            self.held >>= 8
            self.n -= 8

    def close(self) -> bytes:
        return bytes(self.out) + (bytes([self.held & 255]) if self.n else b"")


def lzw_pack(body: bytes, least: int = 8) -> bytes:
    """Codes of growing width, a clear code first and whenever 4096 codes are used up."""
    clear, bits = 1 << least, _Bits()
    width, table, top = least + 1, {}, clear + 2
    bits.put(clear, width)
    prefix = -1
    for b in body:
        if prefix < 0:
            prefix = b
            continue
        key = prefix << 8 | b
        if key in table:
            prefix = table[key]
            continue
        bits.put(prefix, width)
        if top < 4096:
            table[key] = top
            top += 1
            if top > 1 << width and width < 12:
                width += 1
        else:
            bits.put(clear, width)
            width, table, top = least + 1, {}, clear + 2
        prefix = b
    if prefix >= 0:
        bits.put(prefix, width)
        top += top < 4096
        if top > 1 << width and width < 12:
            width += 1
    bits.put(clear + 1, width)
    return bits.close()


def lzw_unpack(packed: bytes, least: int, most: int) -> tuple[bytes, str]:
    """(pixels, how it ended): end, short (codes ran out), bad (a code that no table can hold) or long (too many pixels)."""
    clear, stop = 1 << least, (1 << least) + 1
    width, table, last, held, n = least + 1, [], b"", 0, 0
    out, base = bytearray(), [bytes([i]) for i in range(clear)] + [b"", b""]
    for byte in packed:
        held |= byte << n
        n += 8
        while n >= width:
            code = held & ((1 << width) - 1)
            held >>= width
            n -= width
            if code == clear:
                width, table, last = least + 1, list(base), b""
                continue
            if code == stop:
                return bytes(out), "end"
            if not table or code > len(table) or code == len(table) and not last:
                return bytes(out), "bad"
            word = table[code] if code < len(table) else last + last[:1]
            if last and len(table) < 4096:
                table.append(last + word[:1])
                if len(table) == 1 << width and width < 12:
                    width += 1
            out += word
            if len(out) > most:
                return bytes(out), "long"
            last = word
    return bytes(out), "short"


def gif_encode(number: int, data: bytes) -> bytes:
    body = wrap(number, data)
    rows = -(-len(body) // 64)
    width = 64 if rows <= 65_535 else -(-len(body) // 65_535)
    rows = -(-len(body) // width)
    palette = bytes(x for i in range(256) for x in (i, i, i))
    head = GIF + struct.pack("<HHBBB", width, rows, 0xF7, 0, 0) + palette + b"\x21\xfe" + _blocks(b"%d" % number)
    return head + b"\x2c" + struct.pack("<HHHHB", 0, 0, width, rows, 0) + b"\x08" + _blocks(lzw_pack(body.ljust(width * rows, b"\0"))) + b"\x3b"


def _blocks(data: bytes) -> bytes:
    return b"".join(bytes([len(data[i : i + 255])]) + data[i : i + 255] for i in range(0, len(data), 255)) + b"\0"


def _read_blocks(data: bytes, at: int) -> tuple[bytes, int]:
    """The bytes of a chain of sub-blocks and the place behind it, -1 if it runs out of data."""
    parts = []
    while at < len(data):
        n = data[at]
        if n == 0:
            return b"".join(parts), at + 1
        parts.append(data[at + 1 : at + 1 + n])
        at += 1 + n
    return b"".join(parts), -1


def _gif_walk(data: bytes) -> tuple[Verdict, bytes]:
    if data[:6] not in (GIF, b"GIF87a"):
        return Verdict(), b""
    if len(data) < 13:
        return Verdict(6, more=True), b""
    at, pixels, images = 13 + (3 << (data[10] & 7) + 1 if data[10] & 128 else 0), b"", 0
    good = 13
    while at < len(data):
        good, mark = at, data[at]
        if mark == 0x3B:
            return (Verdict(at + 1, True), pixels) if images else (Verdict(good), b"")
        if mark == 0x21:
            _, end = _read_blocks(data, at + 2)
        elif mark == 0x2C:
            if at + 10 >= len(data):
                break
            width, height, flags = struct.unpack_from("<HHB", data, at + 5)
            start = at + 10 + (3 << (flags & 7) + 1 if flags & 128 else 0)
            if start >= len(data):
                break
            least = data[start]
            if not 2 <= least <= 8 or not width or not height:
                return Verdict(good), b""
            packed, end = _read_blocks(data, start + 1)
            pixels, how = lzw_unpack(packed, least, width * height)
            if how in ("bad", "long") or end > 0 and (how != "end" or len(pixels) != width * height):
                return Verdict(good), b""
            images += 1
        else:
            return Verdict(good), b""
        if end < 0:
            break
        at = good = end
    return Verdict(good, more=True), b""


def gif_check(data: bytes) -> Verdict:
    return _gif_walk(data)[0]


def gif_decode(data: bytes) -> bytes:
    return _gif_walk(data)[1]


# ---------------------------------------------------------------- ELF

ELF = b"\x7fELF\x02\x01\x01"


def elf_encode(number: int, data: bytes) -> bytes:
    """Header, one segment, three sections; the section table is the last thing in the file."""
    body, names = wrap(number, data), b"\0.text\0.bss\0.shstrtab\0"
    at = 64 + 56
    named = at + len(body)
    table = -(-(named + len(names)) // 8) * 8
    head = ELF + bytes(9) + struct.pack("<HHIQQQIHHHHHH", 2, 62, 1, 0x400000, 64, table, 0, 64, 56, 1, 64, 4, 3)
    segment = struct.pack("<IIQQQQQQ", 1, 5, 0, 0x400000, 0x400000, named, named, 0x1000)
    section = lambda name, kind, offset, size: struct.pack("<IIQQQQIIQQ", name, kind, 0, 0, offset, size, 0, 0, 1, 0)
    sections = section(0, 0, 0, 0) + section(1, 1, at, len(body)) + section(7, 8, named, 1 << 40) + section(12, 3, named, len(names))
    return head + segment + body + (names).ljust(table - named, b"\0") + sections


def elf_check(data: bytes) -> Verdict:
    """The span is the largest end of tables, segments and sections; sections that hold no bytes do not count."""
    if not data.startswith(ELF):
        return Verdict()
    if len(data) < 64:
        return Verdict(7, more=True)
    kind, machine, version, _, segments, sections, _, size, ph_size, ph_n, sh_size, sh_n, names = struct.unpack_from("<HHIQQQIHHHHHH", data, 16)
    if not 1 <= kind <= 4 or version != 1 or size != 64 or ph_n and ph_size != 56 or sh_n and (sh_size != 64 or names >= sh_n) or not (ph_n or sh_n):
        return Verdict(16)
    ends = [64, segments + ph_n * 56 if ph_n else 0, sections + sh_n * 64 if sections else 0]
    if max(ends) > len(data):
        return Verdict(64, more=max(ends) < 1 << 40)
    for i in range(ph_n):
        _, _, offset, _, _, held, _, _ = struct.unpack_from("<IIQQQQQQ", data, segments + i * 56)
        ends.append(offset + held)
    if sections:
        for i in range(sh_n):
            name, what, _, _, offset, held, _, _, _, _ = struct.unpack_from("<IIQQQQIIQQ", data, sections + i * 64)
            if what not in (0, 8) and held:
                ends.append(offset + held)
    span = max(ends)
    if span > 1 << 40:
        return Verdict(64)
    return Verdict(span, True) if span <= len(data) else Verdict(64, more=True)


def elf_decode(data: bytes) -> bytes:
    at, size = struct.unpack_from("<QQ", data, struct.unpack_from("<Q", data, 40)[0] + 64 + 24)
    return data[at : at + size]


# ---------------------------------------------------------------- MP3

#: Kilobits a second and samples a second of MPEG-1 layer III (fixed values of the format).
MP3_RATES = (0, 32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320)
MP3_SAMPLES = (44_100, 48_000, 32_000)
MP3_CHAIN, MP3_BODY = 3, 413


def mp3_frame(head: bytes) -> tuple[int, int]:
    """(length, what may not change from frame to frame) of a frame header, length 0 if it is none."""
    if len(head) < 4 or head[0] != 0xFF or head[1] & 0xFE != 0xFA:
        return 0, 0
    rate, sample = head[2] >> 4, head[2] >> 2 & 3
    if rate in (0, 15) or sample == 3:
        return 0, 0
    return 144_000 * MP3_RATES[rate] // MP3_SAMPLES[sample] + (head[2] >> 1 & 1), sample


def mp3_encode(number: int, data: bytes) -> bytes:
    body = wrap(number, data)
    n = max(MP3_CHAIN, -(-len(body) // MP3_BODY))
    tag = b"TIT2" + struct.pack(">IH", 12, 0) + b"\0%011d" % (number % 10**11)
    head = b"ID3\x03\0\0" + bytes([0, 0, len(tag) >> 7, len(tag) & 127]) + tag
    return head + b"".join(b"\xff\xfb\x90\x44" + body[i * MP3_BODY : (i + 1) * MP3_BODY].ljust(MP3_BODY, b"\0") for i in range(n))


def mp3_check(data: bytes) -> Verdict:
    """An optional tag, then frames each of which begins where the one before ends; the file ends where no frame follows."""
    at = 0
    if data.startswith(b"ID3"):
        if len(data) < 10 or max(data[6:10]) > 127:
            return Verdict(3, more=len(data) < 10)
        at = 10 + (data[6] << 21 | data[7] << 14 | data[8] << 7 | data[9])
    chain, kind = 0, None
    while True:
        n, sample = mp3_frame(data[at : at + 4])
        if not n or kind not in (None, sample):
            whole = chain >= MP3_CHAIN and at < len(data)
            return Verdict(min(at, len(data)), whole, not whole and at + 4 > len(data))
        if at + n > len(data):
            return Verdict(at, more=True)
        at, chain, kind = at + n, chain + 1, sample


def mp3_decode(data: bytes) -> bytes:
    at = 10 + (data[8] << 7 | data[9])
    return b"".join(data[i + 4 : i + 4 + MP3_BODY] for i in range(at, len(data), MP3_BODY + 4))


# ---------------------------------------------------------------- ZIP and office documents

ZIP = b"PK\x03\x04"
#: Folders whose entries name an office document (fixed values of the formats).
OFFICE = {"word/": "docx", "xl/": "xlsx", "ppt/": "pptx"}


def _archive(entries: list[tuple[str, bytes, int]]) -> bytes:
    out = io.BytesIO()
    with zipfile.ZipFile(out, "w") as z:
        for name, data, method in entries:
            z.writestr(zipfile.ZipInfo(name, (1980, 1, 1, 0, 0, 0)), data, method)
    return out.getvalue()


def zip_encode(number: int, data: bytes) -> bytes:
    return _archive([("body.bin", wrap(number, data), zipfile.ZIP_DEFLATED), ("name.txt", b"%d" % number, zipfile.ZIP_STORED), ("sum.txt", b"%08x" % zlib.crc32(data), zipfile.ZIP_STORED)])


def docx_encode(number: int, data: bytes) -> bytes:
    return _archive([("[Content_Types].xml", b"<Types/>", zipfile.ZIP_DEFLATED), ("word/document.xml", wrap(number, data), zipfile.ZIP_DEFLATED)])


def zip_entries(data: bytes, end: int) -> list[tuple[str, bytes]] | None:
    """The entries that the end record at ``end`` names, or None unless every one is there and whole."""
    _, disk, _, here, n, size, at, note = struct.unpack_from("<4sHHHHIIH", data, end)
    if disk or here != n or at + size != end or end + 22 + note > len(data):
        return None
    out = []
    for _ in range(n):
        if data[at : at + 4] != b"PK\x01\x02" or at + 46 > end:
            return None
        method, crc, packed, size, name_n, extra_n, note_n = struct.unpack_from("<10xH4xIIIHHH", data, at)
        (local,) = struct.unpack_from("<I", data, at + 42)
        name = data[at + 46 : at + 46 + name_n]
        if data[local : local + 4] != ZIP or local + 30 > end:
            return None
        local_name, local_extra = struct.unpack_from("<HH", data, local + 26)
        begin = local + 30 + local_name + local_extra
        if data[local + 30 : local + 30 + local_name] != name or begin + packed > end or method not in (0, 8):
            return None
        try:
            body = data[begin : begin + packed] if method == 0 else zlib.decompress(data[begin : begin + packed], -15)
        except zlib.error:
            return None
        if len(body) != size or zlib.crc32(body) != crc:
            return None
        out.append((name.decode("utf-8", "replace"), body))
        at += 46 + name_n + extra_n + note_n
    return out


def zip_check(data: bytes) -> Verdict:
    """A whole archive is one whose end record's directory accounts for every entry from the first byte on. Without one, the
    entries that are there whole are consistent."""
    if not data.startswith(ZIP):
        return Verdict()
    end = data.find(b"PK\x05\x06")
    while end >= 0 and end + 22 <= len(data):
        entries = zip_entries(data, end)
        if entries:
            (note,) = struct.unpack_from("<H", data, end + 20)
            label = next((v for k, v in OFFICE.items() if any(name.startswith(k) for name, _ in entries)), "zip")
            return Verdict(end + 22 + note, True, label=label)
        end = data.find(b"PK\x05\x06", end + 4)
    at = 0
    while data[at : at + 4] == ZIP and at + 30 <= len(data):
        flags, crc, packed, name_n, extra_n = struct.unpack_from("<6xH6xII4xHH", data, at)
        if flags & 8 or at + 30 + name_n + extra_n + packed > len(data):
            return Verdict(max(at, 4), more=True)
        at += 30 + name_n + extra_n + packed
    return Verdict(max(at, 4), more=_zip_open(data, at))


def _zip_open(data: bytes, at: int) -> bool:
    """Whether more bytes could complete an archive whose entries end at ``at``. They cannot where no record follows, nor
    behind an end record, as that of an archive of which a later entry was taken for the first one."""
    while data[at : at + 4] == b"PK\x01\x02" and at + 46 <= len(data):
        at += 46 + sum(struct.unpack_from("<HHH", data, at + 28))
    if at + 4 > len(data):
        return True
    if data[at : at + 4] == b"PK\x05\x06":
        return at + 22 > len(data) or at + 22 + struct.unpack_from("<H", data, at + 20)[0] > len(data)
    return data[at : at + 2] == b"PK"


def zip_decode(data: bytes) -> bytes:
    entries = dict(zip_entries(data, data.rfind(b"PK\x05\x06")))
    return entries.get("body.bin") or entries["word/document.xml"]


FORMATS = {
    f.name: f
    for f in (
        Format("png", PNG, png_encode, png_check, png_decode),
        Format("gif", GIF, gif_encode, gif_check, gif_decode),
        Format("elf", ELF, elf_encode, elf_check, elf_decode),
        Format("mp3", b"ID3\x03", mp3_encode, mp3_check, mp3_decode),
        Format("zip", ZIP, zip_encode, zip_check, zip_decode),
        Format("docx", ZIP, docx_encode, zip_check, zip_decode),
    )
}
