"""Baseline JPEG as a media column: decode to DC-only luminance thumbnails in numpy.

The decoder parses the markers of each image, cuts its scan at restart markers and then
Huffman-decodes all segments of all images of a batch in lock step: every numpy step
advances each segment by one symbol, so the loop's length is that of one segment and not
of the batch. AC symbols are read and skipped; the DC values of the first component
are the thumbnail (one sample per 8x8 block).

`store` is the matching writer for arbitrary bytes: one byte per 8x8 block, as a flat
grey block whose DC value is the byte. With a DC quantiser of 8 that value is an
integer, so the thumbnail of the stored image is the payload, exactly.
"""

from __future__ import annotations

import functools
import hashlib
import re
import struct
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from parsieve.llm.common import slices

WIDE = 24  # blocks in a row of a stored payload; a row is a restart interval
UNIT = 576  # bytes to a multiple of which a payload is padded
TALL = 8160  # block rows of one stored image; a longer payload continues in the next one

# Fixed values of the format: the usual luminance DC code (codes of each length 1..16,
# then symbols). The AC code of stored payloads has one symbol, end of block.
DC_COUNTS = (0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0)
DC_SYMBOLS = tuple(range(12))
AC_COUNTS = (1, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0)
AC_SYMBOLS = (0,)


_END = re.compile(rb"\xff+([^\x00\xd0-\xd7\xff])")


class JpegError(ValueError):
    pass


def codes(counts: tuple[int, ...], symbols: tuple[int, ...]) -> dict[int, tuple[int, int]]:
    """symbol -> (code, length) of a canonical Huffman table."""
    out, code, i = {}, 0, 0
    for length, n in enumerate(counts, 1):
        for _ in range(n):
            if i >= len(symbols) or code >> length:
                raise JpegError("bad Huffman table")
            out[symbols[i]] = (code, length)
            code, i = code + 1, i + 1
        code <<= 1
    return out


def lookup(counts: tuple[int, ...], symbols: tuple[int, ...]) -> np.ndarray:
    """For each 16-bit window: code length << 8 | symbol; 0 where no code begins."""
    table = np.zeros(65536, np.uint16)
    for symbol, (code, length) in codes(counts, symbols).items():
        table[code << (16 - length) : (code + 1) << (16 - length)] = length << 8 | symbol
    return table


@functools.lru_cache(32)
def fused(dc: tuple, ac: tuple) -> tuple[np.ndarray, np.ndarray]:
    """For each 16-bit window that holds a DC code, its extra bits and an end of block:
    all their bits, and the DC difference. 0 bits where the window does not."""
    w = np.arange(65536)
    hit = lookup(*dc).astype(np.int64)
    length, size = hit >> 8, np.minimum(hit & 255, 16)
    used = length + size
    fits = (hit > 0) & (used <= 16)
    size, used = np.where(fits, size, 0), np.where(fits, used, 0)
    bits = ((w << length) & 0xFFFF) >> (16 - size)
    diff = np.where((size > 0) & (bits >> np.maximum(size - 1, 0) == 0), bits - (1 << size) + 1, bits)
    code, n = codes(*ac).get(0, (0, 17))
    fits &= (used + n <= 16) & (((w << used) & 0xFFFF) >> max(0, 16 - n) == code)
    return np.where(fits, used + n, 0).astype(np.int64), np.where(fits, diff, 0).astype(np.int32)


class Part(NamedTuple):
    """A component as the frame header gives it, with the tables that its scan names."""

    h: int
    v: int
    quantiser: int
    dc: tuple
    ac: tuple


class Image(NamedTuple):
    width: int
    height: int
    parts: tuple[Part, ...]
    interval: int  # units between restart markers, 0 for none
    scan: tuple[int, int]  # bytes of the entropy-coded data
    end: int

    @property
    def units(self) -> tuple[int, int]:
        """Coded units across and down."""
        if len(self.parts) == 1:
            return -(-self.width // 8), -(-self.height // 8)
        across, down = 8 * max(p.h for p in self.parts), 8 * max(p.v for p in self.parts)
        return -(-self.width // across), -(-self.height // down)


def parse(data: bytes, at: int = 0) -> Image:
    """The baseline image that starts at `at`."""
    if data[at : at + 2] != b"\xff\xd8":
        raise JpegError("no start of image")
    at += 2
    quant: dict[int, int] = {}
    huff: dict[int, tuple] = {}
    frame, interval = None, 0
    while True:
        if at + 4 > len(data) or data[at] != 0xFF:
            raise JpegError("marker expected")
        kind = data[at + 1]
        if kind == 0xFF:
            at += 1
            continue
        (size,) = struct.unpack_from(">H", data, at + 2)
        body = data[at + 4 : at + 2 + size]
        if size < 2 or len(body) != size - 2:
            raise JpegError("truncated segment")
        at += 2 + size
        if kind == 0xDB:
            while body:
                wide = body[0] >> 4
                if len(body) < 65 + 64 * (wide > 0):
                    raise JpegError("truncated quantiser")
                quant[body[0] & 15] = int.from_bytes(body[1 : 2 + (wide > 0)], "big")
                body = body[65 + 64 * (wide > 0) :]
        elif kind == 0xC4:
            while body:
                counts = tuple(body[1:17])
                n = sum(counts)
                if len(body) < 17 + n:
                    raise JpegError("truncated Huffman table")
                huff[body[0]] = (counts, tuple(body[17 : 17 + n]))
                body = body[17 + n :]
        elif kind == 0xC0:
            if len(body) < 6 or len(body) < 6 + 3 * body[5]:
                raise JpegError("truncated frame")
            precision, height, width, n = struct.unpack_from(">BHHB", body)
            if precision != 8 or not height or not width or not n:
                raise JpegError("unsupported frame")
            frame = (width, height, {body[6 + 3 * i]: (body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)})
        elif 0xC1 <= kind <= 0xCF and kind != 0xC8 and kind != 0xCC:
            raise JpegError("not baseline")
        elif kind == 0xDD:
            (interval,) = struct.unpack_from(">H", body)
        elif kind == 0xDA:
            break
    if frame is None or len(body) < 1 or body[0] != len(frame[2]):
        raise JpegError("scan without all components")
    parts = []
    try:
        for i in range(body[0]):
            h, v, q = frame[2][body[1 + 2 * i]]
            tables = body[2 + 2 * i]
            parts.append(Part(h, v, quant[q], huff[tables >> 4], huff[16 | tables & 15]))
    except (KeyError, IndexError):
        raise JpegError("missing table") from None
    if len(parts) == 1:
        parts = [parts[0]._replace(h=1, v=1)]
    mark = _END.search(data, at)  # neither a stuffed FF nor a restart
    if not mark:
        raise JpegError("no end of image")
    if mark[1] != b"\xd9":
        raise JpegError("several scans")
    return Image(frame[0], frame[1], tuple(parts), interval, (at, mark.start()), mark.end())


def _segments(data: bytes, image: Image) -> tuple[np.ndarray, np.ndarray]:
    """Unstuffed bytes of the scan, and the lengths of its restart segments."""
    raw = np.frombuffer(data, np.uint8, image.scan[1] - image.scan[0], image.scan[0])
    after = np.zeros(len(raw), bool)
    after[1:] = raw[:-1] == 255
    mark = after & (raw >= 0xD0) & (raw <= 0xD7)
    drop = (after & (raw == 0)) | mark
    drop[:-1] |= mark[1:]
    kept = np.cumsum(~drop)
    ends = np.append(kept[np.flatnonzero(mark)], kept[-1] if len(kept) else 0)
    return raw[~drop], np.diff(ends, prepend=0)


def decode(blobs: list[tuple[bytes, Image]]) -> list[np.ndarray | None]:
    """DC luminance grids (uint8, one sample per block of the first component) of images
    with any tables and sizes; None where the entropy-coded data is damaged."""
    out: list[np.ndarray | None] = [None] * len(blobs)
    layouts: dict[tuple, list[int]] = {}
    for i, (_, image) in enumerate(blobs):
        layouts.setdefault(tuple((p.h, p.v) for p in image.parts), []).append(i)
    for layout, members in layouts.items():
        _decode_alike(blobs, layout, members, out)
    return out


def _decode_alike(blobs: list, layout: tuple, members: list[int], out: list) -> None:
    tables: dict[tuple, int] = {}
    data, first_bit, limit_bit, todo, owner, start_unit = [], [], [], [], [], []
    offset = 0
    for i in members:
        blob, image = blobs[i]
        raw, lengths = _segments(blob, image)
        total = image.units[0] * image.units[1]
        per = image.interval or total
        n = -(-total // per)
        if len(lengths) != n:
            continue
        begins = offset + np.cumsum(lengths) - lengths
        first_bit.append(8 * begins)
        limit_bit.append(8 * (begins + lengths))
        units = np.full(n, per)
        units[-1] = total - per * (n - 1)
        todo.append(units)
        start_unit.append(per * np.arange(n))
        owner.append(np.full(n, i))
        data.append(raw)
        offset += len(raw)
        for p in image.parts:
            tables.setdefault(p.dc, len(tables))
            tables.setdefault(p.ac, len(tables))
    if not data:
        return
    joined = np.concatenate([*data, np.full(8, 255, np.uint8)]).astype(np.uint32)
    window = (joined[:-3] << 24) | (joined[1:-2] << 16) | (joined[2:-1] << 8) | joined[3:]
    try:
        luts = np.concatenate([lookup(*t) for t in tables])
    except JpegError:
        return
    pos, limit, todo, owner, start = (np.concatenate(x) for x in (first_bit, limit_bit, todo, owner, start_unit))
    last = 8 * (len(window) - 1)

    def peek(at: np.ndarray, n_bits: int = 16) -> np.ndarray:
        return (window[at >> 3] << (at & 7).astype(np.uint32)) >> np.uint32(32 - n_bits)

    def table_of(kind: int, c: int) -> np.ndarray | int:
        named = {i: tables[blobs[i][1].parts[c][kind]] for i in set(owner.tolist())}
        if len(set(named.values())) == 1:
            return next(iter(named.values())) << 16
        slot = np.zeros(max(named) + 1, np.int64)
        slot[list(named)] = list(named.values())
        return slot[owner] << 16

    def fused_of(c: int) -> tuple[np.ndarray | int, np.ndarray, np.ndarray]:
        named = {i: (blobs[i][1].parts[c].dc, blobs[i][1].parts[c].ac) for i in set(owner.tolist())}
        pairs = {p: n for n, p in enumerate(dict.fromkeys(named.values()))}
        steps, diffs = (np.concatenate(x) for x in zip(*(fused(*p) for p in pairs), strict=True))
        if len(pairs) == 1:
            return 0, steps, diffs
        slot = np.zeros(max(named) + 1, np.int64)
        slot[list(named)] = [pairs[p] for p in named.values()]
        return slot[owner] << 16, steps, diffs

    try:
        whole = [fused_of(c) for c in range(len(layout))]
    except JpegError:
        return
    dc_table = [table_of(3, c) for c in range(len(layout))]
    ac_table = [table_of(4, c) for c in range(len(layout))]
    shared = [isinstance(t, int) for t in ac_table]
    n_seg, most = len(pos), int(todo.max())
    per_unit = layout[0][0] * layout[0][1]
    grid = np.zeros((most * per_unit, n_seg), np.int16)
    bad = np.zeros(n_seg, bool)
    level = [np.zeros(n_seg, np.int32) for _ in layout]
    even = bool((todo == most).all())
    for unit in range(most):
        live = None if even else todo > unit
        for c, (h, v) in enumerate(layout):
            for block in range(h * v):
                if live is None:  # blocks without AC values, all segments at once
                    base, steps, diffs = whole[c]
                    at = base + peek(pos)
                    step = steps[at]
                    if step.all():
                        level[c] += diffs[at]
                        pos = np.minimum(pos + step, last)
                        if c == 0:
                            grid[unit * per_unit + block] = level[0]
                        continue
                hit = luts[dc_table[c] + peek(pos)].astype(np.int64)
                size = hit & 255
                bad |= (hit == 0) | (size > 15) if live is None else live & ((hit == 0) | (size > 15))
                size = np.minimum(size, 15)
                bits = (peek(np.minimum(pos + (hit >> 8), last)).astype(np.int64)) >> (16 - size)
                diff = np.where(bits >> np.maximum(size - 1, 0) == 0, bits - (1 << size) + 1, bits)
                diff[size == 0] = 0
                step = (hit >> 8) + size
                if live is not None:
                    diff, step = np.where(live, diff, 0), np.where(live, step, 0)
                level[c] += diff.astype(np.int32)
                pos = np.minimum(pos + step, last)
                if c == 0:
                    grid[unit * per_unit + block] = level[0]
                # AC symbols: those segments that still have coefficients to skip.
                hit = luts[ac_table[c] + peek(pos)].astype(np.int64)
                if live is None and not (hit & 255).any():  # all of them end here
                    bad |= hit == 0
                    pos = np.minimum(pos + (hit >> 8), last)
                    continue
                active = np.arange(n_seg) if live is None else np.flatnonzero(live)
                k = np.ones(len(active), np.int64)
                while len(active):
                    hit = luts[(ac_table[c] if shared[c] else ac_table[c][active]) + peek(pos[active])].astype(np.int64)
                    run, size = (hit & 255) >> 4, hit & 15
                    bad[active] |= hit == 0
                    pos[active] = np.minimum(pos[active] + (hit >> 8) + size, last)
                    k += run + 1
                    more = (k < 64) & ((size > 0) | (run == 15)) & (hit != 0)
                    bad[active] |= (k > 64) & ((size > 0) | (run == 15))
                    active, k = active[more], k[more]
    bad |= pos > limit
    order = np.argsort(owner, kind="stable")
    for part in np.split(order, np.flatnonzero(np.diff(owner[order])) + 1):
        i = int(owner[part[0]])
        if bad[part].any():
            continue
        image, (h, v) = blobs[i][1], layout[0]
        across, down = image.units
        if even:
            units = grid[:, part].T.reshape(-1, per_unit)
        else:
            units = np.concatenate([grid[: todo[s] * per_unit, s].reshape(-1, per_unit) for s in part])
        blocks = units.reshape(down, across, v, h).swapaxes(1, 2).reshape(down * v, across * h)
        blocks = blocks[: -(-image.height * v // (8 * max(p.v for p in image.parts))), : -(-image.width * h // (8 * max(p.h for p in image.parts)))]
        out[i] = np.clip((blocks.astype(np.int32) * image.parts[0].quantiser + 1028) >> 3, 0, 255).astype(np.uint8)


def _header(rows: int) -> bytes:
    def segment(kind: int, body: bytes) -> bytes:
        return struct.pack(">BBH", 0xFF, kind, len(body) + 2) + body

    return b"".join(
        (
            b"\xff\xd8",
            segment(0xDB, bytes([0] + [8] * 64)),
            segment(0xC0, struct.pack(">BHHB", 8, 8 * rows, 8 * WIDE, 1) + bytes([1, 0x11, 0])),
            segment(0xC4, bytes([0x00, *DC_COUNTS, *DC_SYMBOLS])),
            segment(0xC4, bytes([0x10, *AC_COUNTS, *AC_SYMBOLS])),
            segment(0xDD, struct.pack(">H", WIDE)),
            segment(0xDA, bytes([1, 1, 0x00, 0, 63, 0])),
        )
    )


def _symbols() -> tuple[np.ndarray, np.ndarray]:
    """For each difference + 255: its bits with the end-of-block bit, and how many."""
    dc, ac = codes(DC_COUNTS, DC_SYMBOLS), codes(AC_COUNTS, AC_SYMBOLS)
    value, length = np.zeros(511, np.uint32), np.zeros(511, np.int64)
    for d in range(-255, 256):
        size = abs(d).bit_length()
        code, n = dc[size]
        extra = d if d >= 0 else d + (1 << size) - 1
        value[d + 255] = ((code << size | extra) << ac[0][1]) | ac[0][0]
        length[d + 255] = n + size + ac[0][1]
    return value, length


_VALUE, _LENGTH = _symbols()


def store(payloads: list[bytes]) -> list[bytes]:
    """Each payload (a positive multiple of UNIT bytes) as one or more JPEG files."""
    samples = np.frombuffer(b"".join(payloads), np.uint8).astype(np.int64).reshape(-1, WIDE)
    diff = np.diff(samples, axis=1, prepend=128) + 255
    length = np.empty((len(samples), WIDE + 1), np.int64)
    value = np.empty((len(samples), WIDE + 1), np.uint32)
    length[:, :WIDE], value[:, :WIDE] = _LENGTH[diff], _VALUE[diff]
    total = length[:, :WIDE].sum(axis=1)
    length[:, WIDE] = -total % 8
    value[:, WIDE] = (1 << length[:, WIDE]) - 1
    at = np.cumsum(length, axis=1) - length
    word, end = at >> 6, (at & 63) + length
    words = np.zeros(len(samples) * 8, np.uint64)  # a row takes 24 * 15 + 7 bits at most
    base = np.arange(len(samples)) * 8
    value = value.astype(np.uint64)
    for j in range(WIDE + 1):
        v, e, w = value[:, j], end[:, j], base + word[:, j]
        words[w] |= np.where(e <= 64, v << np.maximum(64 - e, 0).astype(np.uint64), v >> np.maximum(e - 64, 0).astype(np.uint64))
        over = np.flatnonzero(e > 64)
        words[w[over] + 1] |= v[over] << (128 - e[over]).astype(np.uint64)
    in_row = (total + length[:, WIDE]) // 8
    coded = words.astype(">u8").view(np.uint8).reshape(-1, 64)[np.arange(64) < in_row[:, None]]
    # Stuff a zero after each FF, and leave two bytes for a restart marker after each row.
    full = coded == 255
    row_end = np.cumsum(in_row)
    row = np.repeat(np.arange(len(samples)), in_row)
    stuffed = np.cumsum(full)
    place = np.arange(len(coded)) + stuffed - full + 2 * row
    out = np.zeros(len(coded) + int(stuffed[-1]) + 2 * len(samples), np.uint8)
    out[place] = coded
    ends = row_end + stuffed[row_end - 1] + 2 * np.arange(1, len(samples) + 1)
    files, r, begin = [], 0, 0
    first = np.concatenate([[0], ends])
    number = np.empty(len(samples), np.int64)
    spans = []
    for p in payloads:
        n = len(p) // WIDE
        for top in range(0, n, TALL):
            rows = min(TALL, n - top)
            number[r : r + rows] = np.arange(rows) % 8
            spans.append((len(files), r, rows))
            r += rows
        files.append([])
    out[ends - 2], out[ends - 1] = 255, 0xD0 + number
    stream = out.tobytes()
    for f, begin, rows in spans:
        files[f] += [_header(rows), stream[first[begin] : first[begin + rows] - 2], b"\xff\xd9"]
    return [b"".join(f) for f in files]


def images(media: bytes) -> list[Image]:
    """All images of a file that holds one or several, one after another."""
    out, at = [], 0
    while at < len(media):
        out.append(parse(media, at))
        at = out[-1].end
    if not out:
        raise JpegError("no image")
    return out


def thumbnails(media: list[bytes | None]) -> list[tuple[list[Image], list[np.ndarray]] | str]:
    """Images and DC grids of each file, or what is wrong with it."""
    found: list = []
    blobs = []
    for m in media:
        try:
            parsed = images(m or b"")
            found.append((parsed, len(blobs)))
            blobs += [(m, i) for i in parsed]
        except (JpegError, struct.error) as error:
            found.append(str(error))
    grids = decode(blobs)
    out = []
    for f in found:
        if isinstance(f, str):
            out.append(f)
        else:
            own = grids[f[1] : f[1] + len(f[0])]
            out.append("damaged scan" if any(g is None for g in own) else (f[0], own))
    return out


def difference_hash(grid: np.ndarray) -> str:
    """64 bits: is each of 8 x 9 box averages brighter than its right neighbour?"""
    h, w = grid.shape
    ys, xs = np.arange(8) * h // 8, np.arange(9) * w // 9
    box = np.add.reduceat(np.add.reduceat(grid.astype(np.int64), ys, axis=0), xs, axis=1)
    mean = box / (np.maximum(1, np.diff(ys, append=h))[:, None] * np.maximum(1, np.diff(xs, append=w)))
    return np.packbits(mean[:, :-1] > mean[:, 1:]).tobytes().hex()


def jpeg_features(media: DataFrame, key: str = "media_id", column: str = "media") -> DataFrame:
    """Dimensions and thumbnail hashes of a binary column with baseline JPEG files.

    Returns key (as string), width, height, components, thumb_width, thumb_height,
    thumb_hash (difference hash), thumb_sha256 and error. A null, empty, damaged or
    non-baseline file has null features and an error; of several images in a file the
    first counts.
    """
    names = ["media_id", "width", "height", "components", "thumb_width", "thumb_height", "thumb_hash", "thumb_sha256", "error"]
    types = [pa.string(), *[pa.int32()] * 5, *[pa.string()] * 3]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "media"):
            rows = []
            for k, t in zip(b.column("media_id").to_pylist(), thumbnails(b.column("media").to_pylist()), strict=True):
                if isinstance(t, str):
                    rows.append((k, *[None] * 7, t))
                else:
                    i, g = t[0][0], t[1][0]
                    rows.append((k, i.width, i.height, len(i.parts), g.shape[1], g.shape[0], difference_hash(g), hashlib.sha256(g.tobytes()).hexdigest(), None))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

    schema = "media_id string, width int, height int, components int, thumb_width int, thumb_height int, thumb_hash string, thumb_sha256 string, error string"
    return media.selectExpr(f"cast(`{key}` as string) as media_id", f"`{column}` as media").mapInArrow(run, schema)


def text_as_jpeg(docs: DataFrame) -> DataFrame:
    """Each text as UTF-8, padded with bytes 255 to a positive multiple of UNIT, stored as
    JPEG and read back; sizes and digests of both, and the thumbnail's features.

    A null text counts as empty. A row per input row. Rows whose bytes did not come back
    would raise: the form is lossless.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, limit=1_000_000):
            raw = [(t or "").encode("utf-8", "surrogatepass") for t in b.column("text").to_pylist()]
            payloads = [r + b"\xff" * (max(1, -(-len(r) // UNIT)) * UNIT - len(r)) for r in raw]
            media = store(payloads)
            rows = []
            for r, m, t in zip(raw, media, thumbnails(media), strict=True):
                if isinstance(t, str):
                    raise JpegError(t)
                grid = np.concatenate(t[1])
                back = grid.tobytes()
                shape = f"{t[0][0].width}x{sum(i.height for i in t[0])}"
                rows.append((len(r), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(m), hashlib.sha256(m).hexdigest(), f"{shape}:{grid.shape[1]}x{grid.shape[0]}:{difference_hash(grid)}"))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 7
            types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, t) for c, t in zip(cols, types, strict=True))], names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return docs.select("doc_id", "text").mapInArrow(run, schema)
