"""Baseline JPEG as a media column: a writer, a parser with Huffman decoding, luminance thumbnails from DC terms alone.

``encode_payload`` keeps bytes losslessly as quantised coefficients: three components without subsampling, 64 bytes a
block, every byte b as the coefficient whose eight magnitude bits are b, restart intervals of one MCU, so that DC terms
stand for themselves. Any baseline decoder reads the files. ``decode`` is general (any Huffman and quantisation tables,
sampling factors, restart intervals, 1 to 4 components, interleaved or single scans); it decodes the segments between
restart markers of many files in lockstep, one symbol of every segment for each numpy step.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import text_of

UNIT = 192
# Zigzag order of the 64 coefficients (row-major place of each), ITU-T T.81 figure A.6.
ZIGZAG = np.array([
    0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28,
    35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63,
])


def pad(raw: bytes, unit: int = UNIT) -> bytes:
    """``raw`` and spaces up to a positive multiple of ``unit``."""
    return raw.ljust(max(1, -(-len(raw) // unit)) * unit, b" ")


def segment(marker: int, body: bytes) -> bytes:
    return bytes([0xFF, marker]) + (len(body) + 2).to_bytes(2, "big") + body


def encode_payload(payload: bytes) -> bytes:
    """A baseline JPEG that holds ``payload`` (a positive multiple of 192 bytes)."""
    n = len(payload) // UNIT
    wide = int(np.ceil(np.sqrt(n)))
    high = -(-n // wide)
    if wide > 8191 or not n or len(payload) % UNIT:
        raise ValueError("a payload of 192 to 12 billion bytes, in multiples of 192, is needed")
    blocks = np.zeros((wide * high, UNIT), np.uint8)
    blocks[:n] = np.frombuffer(payload, np.uint8).reshape(n, UNIT)
    bits = np.zeros((len(blocks), UNIT, 9), np.uint8)  # the one Huffman code, 0, then eight magnitude bits
    bits[:, :, 1:] = np.unpackbits(blocks[:, :, None], axis=2)
    coded = np.packbits(bits.reshape(len(blocks), -1), axis=1)  # 216 bytes an MCU, no fill bits
    size = coded.shape[1]
    full = coded == 0xFF
    stuffed = np.zeros((len(blocks), size, 2), np.uint8)
    stuffed[:, :, 0] = coded
    keep = np.ones((len(blocks), size, 2), bool)
    keep[:, :, 1] = full
    marks = np.empty((len(blocks), 2), np.uint8)
    marks[:, 0], marks[:, 1] = 0xFF, 0xD0 + np.arange(len(blocks)) % 8
    keep_marks = np.ones((len(blocks), 2), bool)
    keep_marks[-1] = False
    scan = np.concatenate([stuffed.reshape(len(blocks), -1), marks], axis=1)[np.concatenate([keep.reshape(len(blocks), -1), keep_marks], axis=1)]
    frame = bytes([8]) + (high * 8).to_bytes(2, "big") + (wide * 8).to_bytes(2, "big") + bytes([3, 1, 0x11, 0, 2, 0x11, 0, 3, 0x11, 0])
    return b"".join([
        b"\xff\xd8", segment(0xFE, b"payload %d" % len(payload)), segment(0xDB, bytes([0]) + bytes([1] * 64)), segment(0xC0, frame),
        segment(0xC4, bytes([0x00, 1] + [0] * 15 + [8])), segment(0xC4, bytes([0x10, 1] + [0] * 15 + [8])), segment(0xDD, b"\0\1"),
        segment(0xDA, bytes([3, 1, 0, 2, 0, 3, 0, 0, 63, 0])), scan.tobytes(), b"\xff\xd9",
    ])


@dataclass
class Component:
    ident: int
    h: int
    v: int
    quant: int
    blocks_wide: int = 0
    blocks_high: int = 0
    at: int = 0


@dataclass
class Picture:
    """What the markers say; coefficients of all blocks in zigzag order, component after component."""

    width: int = 0
    height: int = 0
    components: list[Component] = field(default_factory=list)
    quants: dict[int, np.ndarray] = field(default_factory=dict)
    comment: bytes = b""
    coefficients: np.ndarray | None = None


def lookup(counts: bytes, symbols: bytes) -> np.ndarray:
    """For each 16 bits that may come next: code length times 256 plus symbol; 0 where no code begins so."""
    out, code, at = np.zeros(1 << 16, np.int32), 0, 0
    for length, count in enumerate(counts, 1):
        for _ in range(count):
            low = code << (16 - length)
            out[low : low + (1 << (16 - length))] = length << 8 | symbols[at]
            code, at = code + 1, at + 1
        code <<= 1
    return out


@dataclass
class Segment:
    data: np.ndarray
    places: np.ndarray  # block, component slot and DC/AC tables of every block of the segment, in coding order
    picture: int


def parse(data: bytes, number: int, tables: dict[bytes, int], segments: list[Segment]) -> Picture:
    """Read the markers of one file; its scans' segments are added to ``segments``, its Huffman tables to ``tables``."""
    out, huffman, interval = Picture(), {}, 0
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG")
    i = 2
    while i + 1 < len(data):
        if data[i] != 0xFF:
            raise ValueError("a marker is expected")
        marker = data[i + 1]
        if marker == 0xFF:
            i += 1
            continue
        if marker == 0xD9:
            break
        if 0xD0 <= marker <= 0xD7 or marker == 0x01:
            i += 2
            continue
        n = int.from_bytes(data[i + 2 : i + 4], "big")
        body = data[i + 4 : i + 2 + n]
        i += 2 + n
        if marker == 0xFE:
            out.comment += body
        elif marker == 0xDB:
            while body:
                wide, ident = body[0] >> 4, body[0] & 15
                out.quants[ident] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else "u1").astype(np.int32)
                body = body[65 + 64 * wide :]
        elif marker == 0xC4:
            while body:
                count = sum(body[1:17])
                huffman[body[0]] = tables.setdefault(body[1 : 17 + count], len(tables))
                body = body[17 + count :]
        elif marker == 0xDD:
            interval = int.from_bytes(body[:2], "big")
        elif marker in (0xC0, 0xC1):
            out.height, out.width = int.from_bytes(body[1:3], "big"), int.from_bytes(body[3:5], "big")
            out.components = [Component(*(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k])) for k in range(body[5])]
            most_h, most_v = max(c.h for c in out.components), max(c.v for c in out.components)
            across, down = -(-out.width // (8 * most_h)), -(-out.height // (8 * most_v))
            total = 0
            for c in out.components:
                c.blocks_wide, c.blocks_high, c.at = across * c.h, down * c.v, total
                total += c.blocks_wide * c.blocks_high
            out.coefficients = np.zeros((total, 64), np.int16)
        elif 0xC2 <= marker <= 0xCF and marker != 0xC8 and marker != 0xCC:
            raise ValueError("only baseline files are read")
        elif marker == 0xDA:
            raw = np.frombuffer(data, np.uint8)[i:]
            high = np.flatnonzero(raw[:-1] == 0xFF)
            kinds = raw[high + 1]
            ends = high[(kinds != 0) & ((kinds < 0xD0) | (kinds > 0xD7))]
            stop = int(ends[0]) if len(ends) else len(raw)
            restarts = high[(kinds >= 0xD0) & (kinds <= 0xD7) & (high < stop)]
            plan = scan_places(out, body, huffman)
            per = interval or len(plan)
            stuffing = high[(kinds == 0) & (high < stop)] + 1
            bare = np.delete(raw[:stop], stuffing)
            cuts = restarts - np.searchsorted(stuffing, restarts)
            bounds = zip([0, *(cuts + 2).tolist()], [*cuts.tolist(), len(bare)], strict=True)
            segments += [Segment(bare[x:y], plan[k * per : (k + 1) * per].reshape(-1, 4), number) for k, (x, y) in enumerate(bounds) if k * per < len(plan)]
            i += stop
    return out


def scan_places(picture: Picture, body: bytes, huffman: dict[int, int]) -> np.ndarray:
    """(MCU, block, 4): block, component slot, DC table and AC table of every block of a scan in coding order."""
    parts = []
    chosen = [(next(c for c in picture.components if c.ident == body[1 + 2 * k]), body[2 + 2 * k]) for k in range(body[0])]
    for slot, (c, t) in enumerate(chosen):
        if len(chosen) == 1:
            most_h, most_v = max(x.h for x in picture.components), max(x.v for x in picture.components)
            across, down = -(-picture.width * c.h // (8 * most_h)), -(-picture.height * c.v // (8 * most_v))
            h = v = 1
        else:
            across, down, h, v = c.blocks_wide // c.h, c.blocks_high // c.v, c.h, c.v
        mcu = np.arange(across * down)
        for y in range(v):
            for x in range(h):
                block = c.at + (mcu // across * v + y) * c.blocks_wide + mcu % across * h + x
                parts.append(np.stack([block, np.full_like(mcu, slot), np.full_like(mcu, huffman[t >> 4]), np.full_like(mcu, huffman[16 | t & 15])], axis=1))
    return np.stack(parts, axis=1)


def decode_segments(pictures: list[Picture], segments: list[Segment], tables: dict[bytes, int]) -> None:
    """Huffman-decode all segments in lockstep and fill the pictures' coefficients."""
    if not segments:
        return
    table = np.stack([lookup(x[:16], x[16:]) for x in tables])
    bases = np.concatenate([[0], np.cumsum([len(p.coefficients) for p in pictures])])
    blocks = np.zeros((bases[-1], 64), np.int16)
    flat = blocks.reshape(-1)
    order = sorted(range(len(segments)), key=lambda k: -len(segments[k].places))
    counts = np.array([len(segments[k].places) for k in order])
    begins = np.concatenate([[0], np.cumsum([len(segments[k].data) + 8 for k in order])])
    stream = np.full(begins[-1], 0xFF, np.uint8)
    for k, at in zip(order, begins[:-1], strict=True):
        stream[at : at + len(segments[k].data)] = segments[k].data
    limit = np.array([len(segments[k].data) for k in order]) * 8 + begins[:-1] * 8
    wide = stream.astype(np.int64)
    words = (wide[:-4] << 32) | (wide[1:-3] << 24) | (wide[2:-2] << 16) | (wide[3:-1] << 8) | wide[4:]  # 40 bits from each byte
    places = np.zeros((len(order), counts[0], 4), np.int64)
    for row, k in enumerate(order):
        p = segments[k].places
        places[row, : len(p)] = p
        places[row, : len(p), 0] += bases[segments[k].picture]
    bit = begins[:-1] * 8
    dc = np.zeros((len(order), 4), np.int64)

    def symbol(rows: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Next symbol of the rows' streams, and its magnitude bits' value and count."""
        at = bit[rows]
        window = words[at >> 3] << (24 + (at & 7))
        entry = table[which, (window >> 48) & 0xFFFF]
        length = (entry >> 8).astype(np.int64)
        size = (entry & 15).astype(np.int64)
        if not length.all() or (at + length + size > limit[rows]).any():
            raise ValueError("the scan ends early or holds an unknown code")
        extra = (words[(at + length) >> 3] >> (40 - ((at + length) & 7) - size)) & ((1 << size) - 1)
        bit[rows] = at + length + size
        return (entry >> 4) & 15, size, np.where((size > 0) & (extra < (1 << np.maximum(size - 1, 0))), extra - (1 << size) + 1, extra)

    for step in range(counts[0]):
        rows = np.arange(int(np.searchsorted(-counts, -step, side="left")))
        place = places[rows, step]
        _, _, value = symbol(rows, place[:, 2])
        dc[rows, place[:, 1]] += value
        flat[place[:, 0] * 64] = dc[rows, place[:, 1]]
        base, which, k = place[:, 0] * 64, place[:, 3], np.ones(len(rows), np.int64)
        while len(rows):
            run, size, value = symbol(rows, which)
            k = k + run
            some = size > 0
            if (k[some] > 63).any():
                raise ValueError("a run leaves its block")
            flat[(base + k)[some]] = value[some]
            on = (some | (run == 15)) & (k < 63)
            k = k + 1
            if not on.all():
                rows, base, which, k = rows[on], base[on], which[on], k[on]
    for p, a, b in zip(pictures, bases[:-1], bases[1:], strict=True):
        p.coefficients = blocks[a:b]


def decode(files: list[bytes]) -> list[Picture]:
    tables: dict[bytes, int] = {}
    segments: list[Segment] = []
    pictures = [parse(x, k, tables, segments) for k, x in enumerate(files)]
    decode_segments(pictures, segments, tables)
    return pictures


def payload_of(picture: Picture) -> bytes:
    """The bytes that ``encode_payload`` kept."""
    n = int(picture.comment.removeprefix(b"payload "))
    per = picture.coefficients.reshape(3, -1, 64).transpose(1, 0, 2)[: n // UNIT]
    return np.where(per < 0, per + 255, per).astype(np.uint8).tobytes()


def thumbnail(picture: Picture) -> np.ndarray:
    """Luminance at an eighth of the size, from DC terms alone: one sample a block."""
    c = picture.components[0]
    dc = picture.coefficients[c.at : c.at + c.blocks_wide * c.blocks_high, 0].astype(np.float64) * int(picture.quants[c.quant][0])
    return np.clip(dc / 8 + 128, 0, 255).reshape(c.blocks_high, c.blocks_wide)


def thumbnail_hash(picture: Picture, side: int = 8) -> str:
    """Size, and which cells of a side x side grid over the thumbnail exceed their mean, as hexadecimal bits."""
    small = thumbnail(picture)
    rows, cols = (np.arange(side) * n // side for n in small.shape)
    rows_to, cols_to = (np.maximum((np.arange(side) + 1) * n // side, np.arange(side) * n // side + 1) for n in small.shape)
    sums = np.zeros((small.shape[0] + 1, small.shape[1] + 1))
    sums[1:, 1:] = small.cumsum(0).cumsum(1)
    area = (rows_to - rows)[:, None] * (cols_to - cols)[None, :]
    cells = (sums[np.ix_(rows_to, cols_to)] - sums[np.ix_(rows, cols_to)] - sums[np.ix_(rows_to, cols)] + sums[np.ix_(rows, cols)]) / area
    return f"{picture.width}x{picture.height}:{np.packbits(cells > cells.mean()).tobytes().hex()}"


def encode_column(df: DataFrame, column: str = "text") -> DataFrame:
    """Add ``media``, a JPEG of the column's UTF-8 bytes, and ``n_bytes``, their number before the padding. Null is empty."""
    schema = df.select("doc_id", F.lit(0).cast("long").alias("n_bytes"), F.lit(b"").alias("media")).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                raws = [x.as_py().encode() for x in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(x) for x in raws], pa.int64()), pa.array([encode_payload(pad(x)) for x in raws], pa.binary())], names=["doc_id", "n_bytes", "media"])

    return df.select("doc_id", text_of(column).alias("text")).mapInArrow(run, schema)


def media_features(df: DataFrame, most: int = 1 << 22) -> DataFrame:
    """Decode the column ``media`` and describe it: sizes, digests of what was read back, thumbnail hash.

    Files are decoded together up to ``most`` bytes; a longer one alone. No rows give no rows; a file that is no baseline JPEG is an error.
    """
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    kinds = [df.schema["doc_id"].dataType.simpleString(), "bigint", "bigint", "string", "bigint", "bigint", "string", "string"]

    def describe(part: pa.RecordBatch) -> pa.RecordBatch:
        files = part.column(2).to_pylist()
        out = []
        for data, picture in zip(files, decode(files), strict=True):
            payload = payload_of(picture)
            out.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(data), hashlib.sha256(data).hexdigest(), thumbnail_hash(picture)))
        columns = zip(*out, strict=True)
        return pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(list(x)) for x in columns)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            begin, held = 0, 0
            for i, n in enumerate(len(x.as_buffer()) for x in batch.column(2)):
                if held and held + n > most:
                    yield describe(batch.slice(begin, i - begin))
                    begin, held = i, 0
                held += n
            if begin < batch.num_rows:
                yield describe(batch.slice(begin))

    return df.select("doc_id", "n_bytes", "media").mapInArrow(run, ", ".join(f"{n} {k}" for n, k in zip(names, kinds, strict=True)))


def media_table(docs: DataFrame) -> DataFrame:
    """JPEGs of all texts, read back: a row per document (columns doc_id, text; others are ignored)."""
    return media_features(encode_column(docs))
