"""Payloads as baseline JPEG media columns, with DC-only luminance thumbnails.

Each payload byte is the mean of one flat 8x8 block of a grey image 64 blocks wide: with a DC
quantiser of 8 the quantised DC level is the byte minus 128, so the DC-only thumbnail gives the
payload back exactly. A restart interval of one block row makes every row of blocks decodable by
itself; encoder and decoder work on all rows of a batch in lockstep, in numpy. A payload beyond
one image's 8191 block rows continues in further images, one after another.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, first_columns, map_arrow, materialise, slices, text_bytes

ACROSS = 64
MAX_ROWS = 65_528 // 8

# The luminance DC Huffman code of the baseline standard (codes of each length, symbols).
DC_COUNTS = [0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0]
DC_SYMBOLS = [0, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 11]
#: The only AC symbol used is end of block, with a one-bit code.
AC_COUNTS = [1, *[0] * 15]
AC_SYMBOLS = [0]

SOI, EOI, SOS, DQT, DHT, SOF0, DRI, RST0 = 0xD8, 0xD9, 0xDA, 0xDB, 0xC4, 0xC0, 0xDD, 0xD0


def code_words(counts: list[int], symbols: list[int]) -> dict[int, tuple[int, int]]:
    """symbol -> (code, length) of a canonical Huffman table."""
    out, code, at = {}, 0, 0
    for length, n in enumerate(counts, 1):
        for s in symbols[at : at + n]:
            out[s] = (code, length)
            code += 1
        at, code = at + n, code << 1
    return out


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _header(rows: int) -> bytes:
    quant = bytes([0, 8, *[1] * 63])
    frame = struct.pack(">BHHBBBB", 8, rows * 8, ACROSS * 8, 1, 1, 0x11, 0)
    dc, ac = bytes([0x00, *DC_COUNTS, *DC_SYMBOLS]), bytes([0x10, *AC_COUNTS, *AC_SYMBOLS])
    return b"\xff\xd8" + _segment(DQT, quant) + _segment(SOF0, frame) + _segment(DHT, dc) + _segment(DHT, ac) + _segment(DRI, struct.pack(">H", ACROSS)) + _segment(SOS, bytes([1, 1, 0x00, 0, 63, 0]))


def _encode_rows(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entropy-coded bytes of each row of bytes (rows x 64), stuffed, end to end, and their lengths."""
    level = values.astype(np.int16) - 128
    diff = np.diff(level, axis=1, prepend=np.int16(0))
    size = np.zeros(512, dtype=np.uint8)
    size[1:] = np.floor(np.log2(np.arange(1, 512))).astype(np.uint8) + 1
    kind = size[np.abs(diff)]
    words = code_words(DC_COUNTS, DC_SYMBOLS)
    code = np.array([words[s][0] for s in range(10)], dtype=np.uint32)[kind]
    length = np.array([words[s][1] for s in range(10)], dtype=np.uint8)[kind]
    bits = kind.astype(np.uint32)
    extra = np.where(diff < 0, diff.astype(np.int32) + (1 << kind.astype(np.int32)) - 1, diff).astype(np.uint32)
    word = ((code << bits) | extra) << np.uint32(1)  # the last bit is the end-of-block code, 0
    width = length.astype(np.int64) + kind + 1
    ends = np.cumsum(width, axis=1)
    used = ends[:, -1]
    whole = (used + 7) // 8
    base = np.concatenate([[0], np.cumsum(whole)])
    start = (ends - width + 8 * base[:-1, None]).reshape(-1)
    word, width = word.reshape(-1).astype(np.uint64), width.reshape(-1)
    room = word << (32 - (start & 7) - width).astype(np.uint64)  # at most 19 bits after 7: 32 hold them
    at = start >> 3
    out = np.zeros(int(base[-1]) + 4, dtype=np.float64)
    for k in range(4):
        part = (room >> np.uint64(24 - 8 * k)) & np.uint64(255)
        out += np.bincount(at + k, weights=part, minlength=len(out))
    data = out[: int(base[-1])].astype(np.uint8)
    spare = (8 * whole - used).astype(np.int64)
    data[base[1:] - 1] |= ((1 << spare) - 1).astype(np.uint8)  # padding bits are ones
    marks = data == 0xFF
    held = np.concatenate([[0], np.cumsum(marks)])
    stuffed = np.zeros(len(data) + int(held[-1]), dtype=np.uint8)
    stuffed[np.arange(len(data)) + held[:-1]] = data
    return stuffed, whole + held[base[1:]] - held[base[:-1]]


def encode_payloads(payloads: list[bytes]) -> list[bytes]:
    """Media of each payload; lengths must be positive multiples of 64."""
    if not payloads:
        return []
    values = np.frombuffer(b"".join(payloads), dtype=np.uint8).reshape(-1, ACROSS)
    stuffed, lengths = _encode_rows(values)
    data, cuts = stuffed.tobytes(), [0, *np.cumsum(lengths).tolist()]
    restarts = [bytes([0xFF, RST0 + k]) for k in range(8)]
    out, row = [], 0
    for payload in payloads:
        left, parts = len(payload) // ACROSS, []
        while left:
            rows = min(left, MAX_ROWS)
            parts.append(_header(rows))
            for r in range(rows):
                if r:
                    parts.append(restarts[(r - 1) & 7])
                parts.append(data[cuts[row + r] : cuts[row + r + 1]])
            parts.append(b"\xff\xd9")
            row, left = row + rows, left - rows
        out.append(b"".join(parts))
    return out


@dataclass
class Part:
    """A component: blocks of a coding unit across and down, its quantiser's table."""

    across: int
    down: int
    quant: int


@dataclass
class Scan:
    """Components of a scan with their (DC, AC) tables as they were then, and its coded bytes."""

    parts: list[tuple[int, tuple, tuple]]
    interval: int
    data: bytes


class Image:
    """What the markers of one baseline image say, and its scans."""

    def __init__(self, data: bytes, at: int = 0):
        if data[at : at + 2] != b"\xff\xd8":
            raise ValueError("no start of image")
        self.tables: dict[int, tuple[list[int], list[int]]] = {}
        self.quant: dict[int, int] = {}  # what a table does to the DC level
        self.parts: dict[int, Part] = {}
        self.scans: list[Scan] = []
        self.interval = 0
        at += 2
        while True:
            if data[at : at + 1] != b"\xff":
                raise ValueError("marker expected")
            while data[at + 1] == 0xFF:  # fill bytes
                at += 1
            marker = data[at + 1]
            if marker == EOI:
                break
            (length,) = struct.unpack_from(">H", data, at + 2)
            body, at = data[at + 4 : at + 2 + length], at + 2 + length
            if marker == SOS:
                at = self._scan(body, data, at)
            else:
                self._segment(marker, body)
        if not self.parts or not self.scans:
            raise ValueError("no frame or no scan")
        self.end = at + 2

    def _segment(self, marker: int, body: bytes) -> None:
        if marker == DQT:
            while body:
                wide = body[0] >> 4
                self.quant[body[0] & 15] = struct.unpack_from(">H" if wide else ">B", body, 1)[0]
                body = body[1 + 64 * (1 + wide) :]
        elif marker == SOF0:
            depth, self.height, self.width, count = struct.unpack_from(">BHHB", body)
            if depth != 8 or not self.height or not self.width:
                raise ValueError("8-bit samples and known dimensions expected")
            for name, shape, quant in struct.iter_unpack("BBB", body[6 : 6 + 3 * count]):
                self.parts[name] = Part(shape >> 4, shape & 15, quant)
        elif marker == DHT:
            while body:
                counts = list(body[1:17])
                self.tables[body[0]] = counts, list(body[17 : 17 + sum(counts)])
                body = body[17 + sum(counts) :]
        elif marker == DRI:
            (self.interval,) = struct.unpack(">H", body)
        elif 0xC0 <= marker <= 0xCF and marker != 0xC8:
            raise ValueError("only baseline frames are read")

    def _scan(self, body: bytes, data: bytes, at: int) -> int:
        chosen = struct.iter_unpack("BB", body[1 : 1 + 2 * body[0]])
        parts = [(name, self.tables[pair >> 4], self.tables[16 | (pair & 15)]) for name, pair in chosen]
        end = at
        while True:  # a 0xFF inside the scan is stuffed or a restart
            end = data.index(b"\xff", end)
            if data[end + 1] != 0 and not RST0 <= data[end + 1] < RST0 + 8:
                break
            end += 2
        self.scans.append(Scan(parts, self.interval, data[at:end]))
        return end

    def is_payload(self) -> bool:
        """Whether the image has the shape that ``encode_payloads`` writes."""
        one = len(self.parts) == 1 and len(self.scans) == 1
        return one and self.interval == ACROSS and self.width == ACROSS * 8 and self.height % 8 == 0 and list(self.scans[0].parts[0][2][1]) == AC_SYMBOLS


def images(data: bytes) -> Iterator[Image]:
    at = 0
    while at < len(data):
        image = Image(data, at)
        yield image
        at = image.end


def _read_levels(image: Image, scan: Scan) -> dict[int, np.ndarray]:
    """DC levels of each component in the scan, block by block; AC coefficients are passed over."""
    most = max(p.across for p in image.parts.values()), max(p.down for p in image.parts.values())
    size = {}
    for name, p in image.parts.items():
        size[name] = tuple(-(-(-(-n * k // m)) // 8) for n, k, m in ((image.width, p.across, most[0]), (image.height, p.down, most[1])))
    if len(scan.parts) == 1:  # blocks in raster order, without those that only fill a unit
        units = size[scan.parts[0][0]]
        shape = {scan.parts[0][0]: (1, 1)}
    else:
        units = -(-image.width // (8 * most[0])), -(-image.height // (8 * most[1]))
        shape = {name: (image.parts[name].across, image.parts[name].down) for name, _, _ in scan.parts}
    levels = {name: np.zeros((units[1] * v, units[0] * h), dtype=np.int64) for name, (h, v) in shape.items()}
    codes = {name: (_windows(*dc).tolist(), _windows(*ac).tolist()) for name, dc, ac in scan.parts}
    count = units[0] * units[1]
    step = scan.interval or count
    runs = re.split(rb"\xff+[\xd0-\xd7]", scan.data)
    if len(runs) != -(-count // step):
        raise ValueError("restart intervals are missing")
    for number, run in enumerate(runs):
        data = np.frombuffer(run.replace(b"\xff\x00", b"\xff") + bytes(8), dtype=np.uint8).astype(np.int64)
        wide = sum(data[k : len(data) - 4 + k] << (32 - 8 * k) for k in range(5)).tolist()  # 40 bits from each byte
        end, bit, before = 8 * (len(data) - 8), 0, dict.fromkeys(levels, 0)
        for unit in range(number * step, min(count, (number + 1) * step)):
            row, column = divmod(unit, units[0])
            for name, _, _ in scan.parts:
                dc, ac = codes[name]
                for block in range(shape[name][0] * shape[name][1]):
                    found = dc[(wide[bit >> 3] >> (24 - (bit & 7))) & 0xFFFF]
                    bits, bit = found >> 5, bit + (found & 31)
                    extra = (wide[bit >> 3] >> (40 - (bit & 7) - bits)) & ((1 << bits) - 1)
                    bit += bits
                    before[name] += extra - (1 << bits) + 1 if bits and extra < 1 << (bits - 1) else extra
                    down, across = divmod(block, shape[name][0])
                    levels[name][row * shape[name][1] + down, column * shape[name][0] + across] = before[name]
                    k = 1
                    while k < 64:
                        code = ac[(wide[bit >> 3] >> (24 - (bit & 7))) & 0xFFFF]
                        if not found or not code or bit > end:
                            raise ValueError("damaged scan")
                        bit += (code & 31) + ((code >> 5) & 15)
                        if code >> 5 == 0:  # end of block
                            break
                        k += (code >> 9) + 1
    return {name: x[: size[name][1], : size[name][0]] for name, x in levels.items()}


def luminance_thumbnail(image: Image) -> np.ndarray:
    """One sample for each 8x8 block of the first component: its mean, from the DC level alone."""
    name, part = next(iter(image.parts.items()))
    for scan in image.scans:
        if any(name == held for held, _, _ in scan.parts):
            levels = _read_levels(image, scan)[name]
            return np.clip((levels * image.quant[part.quant] + 4) // 8 + 128, 0, 255).astype(np.uint8)
    raise ValueError("no scan of the first component")


def _windows(counts: list[int], symbols: list[int]) -> np.ndarray:
    """For each 16-bit window: symbol * 32 + code length."""
    out = np.zeros(1 << 16, dtype=np.uint16)
    for s, (code, n) in code_words(counts, symbols).items():
        out[code << (16 - n) : (code + 1) << (16 - n)] = s * 32 + n
    return out


def _decode_rows(scans: list[bytes], rows: int, dc: tuple, ac: tuple) -> np.ndarray:
    """DC levels (rows x 64) of restart intervals, all decoded in lockstep."""
    raw = np.frombuffer(b"".join(s + b"\xff\xd0" for s in scans), dtype=np.uint8)
    ff = np.flatnonzero(raw[:-1] == 0xFF)
    after = raw[ff + 1]
    keep = np.ones(len(raw), dtype=bool)
    keep[ff[after == 0] + 1] = False
    marks = ff[(after >= RST0) & (after < RST0 + 8)]
    keep[marks] = keep[marks + 1] = False
    place = np.concatenate([[0], np.cumsum(keep)])
    begin = np.concatenate([[0], place[marks[:-1] + 2]]) * 8
    if len(begin) != rows:
        raise ValueError("restart intervals are missing")
    data = np.concatenate([raw[keep], np.zeros(8, np.uint8)]).astype(np.uint64)
    wide = (data[:-4] << np.uint64(32)) | (data[1:-3] << np.uint64(24)) | (data[2:-2] << np.uint64(16)) | (data[3:-1] << np.uint64(8)) | data[4:]
    dc_window, ac_window = _windows(*dc), _windows(*ac)
    out = np.empty((rows, ACROSS), dtype=np.int32)
    bit, level = begin.astype(np.int64), np.zeros(rows, dtype=np.int64)
    for column in range(ACROSS):
        window = wide[bit >> 3] << (bit & 7).astype(np.uint64)  # 40 bits, those to read at the top
        found = dc_window[((window >> np.uint64(24)) & np.uint64(0xFFFF)).astype(np.int64)].astype(np.int64)
        kind, n = found >> 5, found & 31
        extra = ((window >> (40 - n - kind).astype(np.uint64)) & ((np.uint64(1) << kind.astype(np.uint64)) - np.uint64(1))).astype(np.int64)
        level = level + np.where((kind > 0) & (extra < (1 << np.maximum(kind - 1, 0))), extra - (1 << kind) + 1, extra)
        out[:, column] = level
        bit = bit + n + kind
        window = wide[bit >> 3] << (bit & 7).astype(np.uint64)
        block = ac_window[((window >> np.uint64(24)) & np.uint64(0xFFFF)).astype(np.int64)].astype(np.int64)
        if (block >> 5).any() or not block.all():
            raise ValueError("only end-of-block AC codes are expected")
        bit = bit + (block & 31)
    return out


def read_thumbnails(media: list[bytes]) -> list[tuple[bytes, list[tuple[int, int]]]]:
    """(thumbnail bytes, (width, height) of each image) of each media value, which may hold several
    baseline images. Images as ``encode_payloads`` writes them are decoded in lockstep, others one
    by one."""
    parsed = [list(images(m)) for m in media]
    alike: dict[str, list[Image]] = {}
    thumbnails: dict[int, bytes] = {}
    for image in (i for group in parsed for i in group):
        if image.is_payload():
            alike.setdefault(repr(image.scans[0].parts), []).append(image)
        else:
            thumbnails[id(image)] = luminance_thumbnail(image).tobytes()
    for group in alike.values():
        _, dc, ac = group[0].scans[0].parts[0]
        rows = [i.height // 8 for i in group]
        levels = _decode_rows([i.scans[0].data for i in group], sum(rows), dc, ac)
        quant = np.repeat([i.quant[next(iter(i.parts.values())).quant] for i in group], rows)
        samples = np.clip((levels * quant[:, None] + 4) // 8 + 128, 0, 255).astype(np.uint8)
        for image, low, n in zip(group, np.cumsum(rows) - rows, rows):
            thumbnails[id(image)] = samples[low : low + n].tobytes()
    return [(b"".join(thumbnails[id(i)] for i in group), [(i.width, i.height) for i in group]) for group in parsed]


def thumbnail_hash(thumbnail: bytes) -> str:
    """64-bit average hash: the thumbnail's rows pooled to 8 bands of 8 cells, each against the mean."""
    grey = np.frombuffer(thumbnail, dtype=np.uint8).reshape(-1, ACROSS).astype(np.float64)
    bands = np.add.reduceat(grey, (np.arange(8) * len(grey)) // 8, axis=0)
    rows = np.maximum(1, np.diff(np.append((np.arange(8) * len(grey)) // 8, len(grey))))
    cells = bands.reshape(8, 8, 8).sum(axis=2) / rows[:, None]
    return np.packbits(cells > cells.mean()).tobytes().hex()


def pad(text: bytes) -> bytes:
    """Zero bytes up to a positive multiple of 64."""
    return text + b"\0" * ((-len(text)) % ACROSS or (0 if text else ACROSS))


def media_column(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media binary): each whole text as media; null text counts as empty."""
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.large_binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text", 1 << 20):
            raw = text_bytes(part.column("text"))
            media = encode_payloads([pad(t) for t in raw])
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(map(len, raw), pa.int64()), pa.array(media, pa.large_binary())], schema=schema)

    return map_arrow(first_columns(docs, "doc_id", "text"), run, "doc_id long, n_bytes long, media binary")


def store_and_read(docs: DataFrame, rounds: int = 4) -> DataFrame:
    """Stores each whole text as media in the shared folder, reads the stored bytes back and digests
    both: (doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256,
    feature). The feature holds the images' dimensions and the thumbnail's average hash. Null text
    counts as empty: one block row of zeros; repeated rows are stored each; an empty table gives an
    empty result; other columns are ignored.

    Entropy-coded media hardly compress, so all of them take more room than their Parquet source.
    The rows are dealt into ``rounds`` parts; a part's media go when their digests are written.
    """
    slim = first_columns(docs, "doc_id", "text")
    dealt = F.pmod(F.xxhash64("doc_id", "text"), F.lit(rounds))
    found = []
    for k in range(rounds):
        stored = materialise(media_column(slim.where(dealt == k)), "media")
        found.append(materialise(read_media(stored), "media-digests"))
        discard(stored)
    return reduce(DataFrame.unionByName, found)


def _digests(ids: pa.Array, sizes: list[int], media: list[bytes], schema: pa.Schema) -> pa.RecordBatch:
    rows = []
    for stored, (payload, dims) in zip(media, read_thumbnails(media), strict=True):
        shape = "+".join(f"{w}x{h}" for w, h in dims)
        rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), f"jpeg:{shape}:{thumbnail_hash(payload)}"))
    columns = list(zip(*rows, strict=True))
    return pa.RecordBatch.from_arrays([ids.cast(pa.int64()), pa.array(sizes, pa.int64()), *[pa.array(c, f.type) for c, f in zip(columns, list(schema)[2:], strict=True)]], schema=schema)


DIGESTS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _digest_schema() -> pa.Schema:
    kinds = {"long": pa.int64(), "string": pa.string()}
    return pa.schema([(n, kinds[k]) for n, k in (x.split() for x in DIGESTS.split(", "))])


def read_media(stored: DataFrame) -> DataFrame:
    """The same digests from a stored (doc_id, n_bytes, media) table; null media is an error."""
    schema = _digest_schema()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "media", 1 << 20):
            yield _digests(part.column("doc_id"), part.column("n_bytes").to_pylist(), part.column("media").to_pylist(), schema)

    return map_arrow(first_columns(stored, "doc_id", "n_bytes", "media"), run, DIGESTS)
