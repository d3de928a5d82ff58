"""Media columns: baseline JPEG.

``parse`` reads the markers of a baseline stream, ``dc_planes`` Huffman-decodes the scans of many streams at once and
returns each one's luminance at an eighth of its size, from the DC coefficients alone; ``features`` adds dimensions
and hashes of that thumbnail. ``store`` writes bytes as the DC coefficients of flat blocks, with a quantiser under
which a block's mean is its byte: the thumbnail of the stored stream is the payload, byte for byte.

The decoder works on all restart intervals of a group of streams side by side, one block a step.

Defined cases: a null or empty text is a payload of one unit of padding; a payload above ``MOST_ROWS`` rows of blocks
goes into several streams laid end to end; of components in scans of their own, the first's is decoded; a damaged or non-baseline stream raises ``ValueError``; repeated rows give equal values.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh, table, travels
from .textkit import slabs, spans

travels(__name__)

#: Payload bytes come in multiples of this many; a row of blocks has NARROW bytes, or WIDE when a stream grows long.
UNIT, NARROW, WIDE, MOST_ROWS = 576, 24, 576, 8191
#: What our streams use. DC categories 0 to 8 by code length, one AC code (end of block) of one bit.
DC_LENGTHS = {0: 2, 3: 3, 4: 3, 5: 3, 6: 3, 7: 3, 2: 5, 1: 5, 8: 5}
#: Fixed values of the format: the order in which a block's coefficients are stored.
ZIGZAG = [i for _, i in sorted(((r + c, (r if (r + c) % 2 else c)), r * 8 + c) for r in range(8) for c in range(8))]


# ---- Huffman tables -------------------------------------------------------------------------------------------------


def table_of(lengths: dict[int, int]) -> tuple[bytes, bytes]:
    """Counts of codes by length and the symbols in order of code, as a DHT segment holds them."""
    symbols = sorted(lengths, key=lambda s: lengths[s])
    return bytes(sum(v == n for v in lengths.values()) for n in range(1, 17)), bytes(symbols)


def codes_of(counts: bytes, symbols: bytes) -> dict[int, tuple[int, int]]:
    """Symbol -> (code, length): codes of a length count up, and double from one length to the next."""
    out, code, at = {}, 0, 0
    for n in range(1, 17):
        for s in symbols[at : at + counts[n - 1]]:
            out[s] = (code, n)
            code += 1
        at += counts[n - 1]
        code <<= 1
    return out


def lookup(counts: bytes, symbols: bytes) -> np.ndarray:
    """For every 16 bits that may come next: length << 8 | symbol, or 0 where no code fits."""
    out = np.zeros(1 << 16, np.int32)
    for s, (code, n) in codes_of(counts, symbols).items():
        lo = code << (16 - n)
        out[lo : lo + (1 << (16 - n))] = n << 8 | s
    return out


# ---- storing --------------------------------------------------------------------------------------------------------


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def headers(rows: int, width: int) -> bytes:
    quant = bytes([0]) + bytes([8] + [1] * 63)
    frame = struct.pack(">BHHB", 8, rows * 8, width * 8, 1) + bytes([1, 0x11, 0])
    dc, ac = table_of(DC_LENGTHS), table_of({0: 1})
    huff = b"".join(bytes([k]) + c + s for k, (c, s) in ((0x00, dc), (0x10, ac)))
    return b"\xff\xd8" + _segment(0xDB, quant) + _segment(0xC0, frame) + _segment(0xC4, huff) + _segment(0xDD, struct.pack(">H", width)) + _segment(0xDA, bytes([1, 1, 0, 0, 63, 0]))


def scans(payload: np.ndarray, row_of: np.ndarray, n_rows: int, row_in_stream: np.ndarray, last_row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entropy-coded data of many rows of blocks, each a restart interval, and where each row's data starts.

    ``row_of`` gives the row of each byte; a row ends with its restart marker unless it is the last of its stream."""
    value = payload.astype(np.int64) - 128
    diff = value.copy()
    diff[1:] -= value[:-1]
    firsts = np.flatnonzero(np.r_[True, row_of[1:] != row_of[:-1]])
    diff[firsts] = value[firsts]
    size = np.zeros(len(diff), np.int64)
    for k in range(8):
        size += np.abs(diff) >= (1 << k)
    codes = codes_of(*table_of(DC_LENGTHS))
    code, clen = (np.array([codes[k][i] for k in range(9)]) for i in (0, 1))
    extra = np.where(diff < 0, diff + (1 << size) - 1, diff)
    bits = ((code[size] << size) | extra) << 1  # the end-of-block code is a 0
    n = clen[size] + size + 1
    ends = np.cumsum(n)
    row_bits = np.diff(np.r_[0, ends[np.r_[firsts[1:] - 1, len(ends) - 1]]])
    row_bytes = (row_bits + 7) // 8
    row_at = spans(row_bytes)
    shift = row_at[:-1] * 8 - (np.cumsum(row_bits) - row_bits)
    at = ends - n + shift[row_of]
    word, inside = at >> 5, at & 31
    up = bits << (64 - n - inside)  # at most 64 bits from the word's start: n <= 14
    total = int(row_at[-1] + 7) // 4 + 2
    hi = np.bincount(word, weights=((up >> 32) & 0xFFFFFFFF).astype(float), minlength=total)
    lo = np.bincount(word + 1, weights=(up & 0xFFFFFFFF).astype(float), minlength=total)
    raw = (hi[:total] + lo[:total]).astype(np.uint64).astype(">u4").view(np.uint8)[: row_at[-1]].copy()
    pad = row_bytes * 8 - row_bits
    raw[row_at[1:] - 1] |= ((1 << pad) - 1).astype(np.uint8)
    # a zero byte after each 255, a marker after each row but the last of a stream
    grow = np.ones(len(raw), np.int64) + (raw == 255)
    close = row_at[1:] - 1
    grow[close] += np.where(last_row, 0, 2)
    to = spans(grow)
    out = np.zeros(to[-1], np.uint8)
    out[to[:-1]] = raw
    marked = close[~last_row]
    out[to[marked + 1] - 2] = 255
    out[to[marked + 1] - 1] = 0xD0 + (row_in_stream[~last_row] & 7)
    return out, np.r_[to[row_at[:-1]], to[-1]]


def store(payloads: list[bytes]) -> list[bytes]:
    """Each payload (a positive multiple of UNIT bytes) as one or more baseline streams end to end."""
    pieces: list[tuple[int, int, int]] = []  # payload, rows, width
    for k, p in enumerate(payloads):
        if len(p) // NARROW <= MOST_ROWS:
            pieces.append((k, len(p) // NARROW, NARROW))
        else:
            rows = len(p) // WIDE
            pieces += [(k, min(MOST_ROWS, rows - lo), WIDE) for lo in range(0, rows, MOST_ROWS)]
    rows = np.array([r for _, r, _ in pieces])
    widths = np.repeat(np.array([w for _, _, w in pieces]), rows)
    data = np.frombuffer(b"".join(payloads), np.uint8)
    first = spans(rows)
    row_in_stream = np.arange(first[-1]) - np.repeat(first[:-1], rows)
    body, at = scans(data, np.repeat(np.arange(len(widths)), widths), len(widths), row_in_stream, row_in_stream == np.repeat(rows, rows) - 1)
    out = [b""] * len(payloads)
    for (k, r, w), a in zip(pieces, range(len(pieces)), strict=True):
        out[k] += headers(r, w) + body[at[first[a]] : at[first[a + 1]]].tobytes() + b"\xff\xd9"
    return out


# ---- reading --------------------------------------------------------------------------------------------------------


@dataclass
class Stream:
    """One parsed baseline image: its frame, and the place and tables of the scan that holds its luminance."""

    width: int = 0
    height: int = 0
    parts: list[tuple[int, int, int, int]] = field(default_factory=list)  # id, h, v, quantiser
    quant: dict[int, int] = field(default_factory=dict)  # the DC entry of each table
    huff: dict[int, tuple[bytes, bytes]] = field(default_factory=dict)
    every: int = 0
    scan: list[tuple[int, int, int]] = field(default_factory=list)  # component, dc table, ac table
    begin: int = 0
    end: int = 0

    @property
    def key(self) -> tuple:
        return (tuple(self.parts), tuple(self.scan), tuple(sorted(self.quant.items())), tuple(sorted(self.huff.items())))


def parse(data: bytes) -> list[Stream]:
    """All baseline images that stand end to end in ``data``."""
    out, at = [], 0
    while at < len(data):
        if data[at : at + 2] != b"\xff\xd8":
            raise ValueError("a stream must start with SOI")
        s, found, at = Stream(), None, at + 2
        while True:
            if at + 2 > len(data) or data[at] != 0xFF:
                raise ValueError("marker expected")
            marker = data[at + 1]
            at += 2
            if marker == 0xFF:
                at -= 1
                continue
            if marker == 0xD9:
                break
            (size,) = struct.unpack(">H", data[at : at + 2])
            body, at = data[at + 2 : at + size], at + size
            if marker == 0xDB:
                while body:
                    wide = body[0] >> 4
                    s.quant[body[0] & 15] = struct.unpack(">H", body[1:3])[0] if wide else body[1]
                    body = body[1 + 64 * (1 + wide) :]
            elif marker == 0xC0:
                _, s.height, s.width, n = struct.unpack(">BHHB", body[:6])
                s.parts = [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)]
            elif marker == 0xC4:
                while body:
                    n = sum(body[1:17])
                    s.huff[body[0]] = (body[1:17], body[17 : 17 + n])
                    body = body[17 + n :]
            elif marker == 0xDD:
                (s.every,) = struct.unpack(">H", body)
            elif marker == 0xDA:
                scan, begin = [(body[1 + 2 * i], body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15) for i in range(body[0])], at
                while True:
                    at = data.find(b"\xff", at)
                    if at < 0 or at + 1 >= len(data):
                        raise ValueError("the scan doesn't end")
                    if data[at + 1] == 0 or 0xD0 <= data[at + 1] <= 0xD7:
                        at += 2
                        continue
                    break
                # components may come in scans of their own, with new tables between them: what holds for luminance's counts
                if found is None and s.parts and s.parts[0][0] in [c for c, _, _ in scan]:
                    found = replace(s, quant=dict(s.quant), huff=dict(s.huff), scan=scan, begin=begin, end=at)
            elif 0xC1 <= marker <= 0xCF and marker != 0xC8 and marker != 0xCC:
                raise ValueError("not a baseline stream")
        if found is None or not found.width or not found.height:
            raise ValueError("no frame or no scan of luminance")
        out.append(found)
    return out


def _intervals(streams: list[tuple[bytes, Stream]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The scans' data without stuffed zeros and markers; where each restart interval starts; intervals by stream."""
    raw = np.frombuffer(b"".join(d[s.begin : s.end] + b"\xff\xd0" for d, s in streams), np.uint8)
    mark = np.zeros(len(raw), bool)
    ff = np.flatnonzero(raw[:-1] == 255)
    mark[ff[raw[ff + 1] != 0]] = True
    stuffed = np.zeros(len(raw), bool)
    stuffed[ff[raw[ff + 1] == 0] + 1] = True
    close = np.flatnonzero(mark)
    drop = mark | stuffed
    drop[close + 1] = True
    kept_before = spans((~drop).astype(np.int64))
    starts = np.r_[0, kept_before[close[:-1]]]
    sizes = spans(np.array([s.end - s.begin + 2 for _, s in streams]))
    per = np.diff(np.searchsorted(close, sizes))
    return raw[~drop], starts, per


def dc_planes(datas: list[bytes]) -> list[list[np.ndarray]]:
    """For each item the luminance thumbnails of its images: one 8-bit sample for each 8 x 8 block."""
    parsed = [(k, d, s) for k, d in enumerate(datas) for s in parse(d)]
    out: list[list] = [[] for _ in datas]
    slots = {}
    for n, (k, _, _) in enumerate(parsed):
        slots[n] = (k, len(out[k]))
        out[k].append(None)
    groups: dict[tuple, list[int]] = {}
    for n, (_, _, s) in enumerate(parsed):
        groups.setdefault(s.key, []).append(n)
    for members in groups.values():
        for n, plane in zip(members, _decode([(parsed[n][1], parsed[n][2]) for n in members]), strict=True):
            k, i = slots[n]
            out[k][i] = plane
    return out


def _decode(streams: list[tuple[bytes, Stream]]) -> list[np.ndarray]:
    """Luminance DC planes of streams with equal tables."""
    first = streams[0][1]
    bytes_, starts, per = _intervals(streams)
    big = np.concatenate([bytes_, np.zeros(8, np.uint8)]).astype(np.int64)
    window = (big[:-4] << 32) | (big[1:-3] << 24) | (big[2:-2] << 16) | (big[3:-1] << 8) | big[4:]
    most = len(window) - 1
    table_dc = {t: lookup(*first.huff[t]) for _, t, _ in first.scan}
    table_ac = {t: lookup(*first.huff[0x10 | t]) for _, _, t in first.scan}
    shape = {c: (h, v) for c, h, v, _ in first.parts}
    hm, vm = max(h for h, _ in shape.values()), max(v for _, v in shape.values())
    luma = first.parts[0][0]
    ph, pv = hm // shape[luma][0], vm // shape[luma][1]
    if len(first.scan) == 1:  # a single component is not interleaved: a unit is one of its blocks
        shape, hm, vm = {luma: (1, 1)}, ph, pv
    units_x = np.array([-(-s.width // (8 * hm)) for _, s in streams])
    units = units_x * np.array([-(-s.height // (8 * vm)) for _, s in streams])
    every = np.array([s.every or u for (_, s), u in zip(streams, units.tolist(), strict=True)])
    if (per != -(-units // every)).any():
        raise ValueError("the restart intervals don't match the frame")
    owner = np.repeat(np.arange(len(streams)), per)
    inner = np.arange(len(owner)) - np.repeat(np.cumsum(per) - per, per)
    todo = np.minimum(every[owner], units[owner] - inner * every[owner])
    order = np.argsort(-todo, kind="stable")
    todo, bit = todo[order], starts[order] * 8
    blocks = shape[luma][0] * shape[luma][1]
    at = spans(units * blocks)
    base = at[owner[order]] + inner[order] * every[owner[order]] * blocks
    coef = np.zeros(at[-1], np.int64)
    pred = {c: np.zeros(len(todo), np.int64) for c, _, _ in first.scan}

    def peek(pos):
        return (window[np.minimum(pos >> 3, most)] >> (24 - (pos & 7))) & 0xFFFF

    def take(pos, n):
        x = window[np.minimum(pos >> 3, most)] >> (40 - (pos & 7) - n)
        return x & ((1 << n) - 1)

    steps = int(todo[0]) if len(todo) else 0
    for t in range(steps):
        k = int(np.searchsorted(-todo, -t, "left"))
        pos = bit[:k]
        for c, dc, ac in first.scan:
            for b in range(shape[c][0] * shape[c][1]):
                hit = table_dc[dc][peek(pos)]
                if not hit.all():
                    raise ValueError("no such code")
                size = hit & 255
                pos = pos + (hit >> 8)
                x = take(pos, size)
                pos = pos + size
                pred[c][:k] += np.where((size > 0) & (x < (1 << np.maximum(size - 1, 0))), x - (1 << size) + 1, x)
                if c == luma:
                    coef[base[:k] + t * blocks + b] = pred[c][:k]
                left, index = np.arange(k), np.ones(k, np.int64)
                while len(left):
                    hit = table_ac[ac][peek(pos[left])]
                    if not hit.all():
                        raise ValueError("no such code")
                    run, size = (hit >> 4) & 15, hit & 15
                    pos[left] += (hit >> 8) + size
                    index = index + run + 1
                    go = ((size > 0) | (run == 15)) & (index < 64)
                    left, index = left[go], index[go]
        bit[:k] = pos
    q = first.quant[next(p[3] for p in first.parts if p[0] == luma)]
    sample = np.clip((coef * q + 4 + 1024) >> 3, 0, 255).astype(np.uint8)
    planes = []
    for n, (_, s) in enumerate(streams):
        h, v = shape[luma]
        x = sample[at[n] : at[n + 1]].reshape(-1, units_x[n], v, h).swapaxes(1, 2).reshape(-1, units_x[n] * h)
        planes.append(x[: -(-s.height // (8 * pv)), : -(-s.width // (8 * ph))])
    return planes


def thumbnail_hash(plane: np.ndarray, side: int = 8) -> str:
    """64 bits in hexadecimal: which cells of a ``side`` x ``side`` grid are lighter than the one to their left."""
    rows = (np.arange(side) * plane.shape[0] // side).clip(0, plane.shape[0] - 1)
    cols = (np.arange(side + 1) * plane.shape[1] // (side + 1)).clip(0, plane.shape[1] - 1)
    total = np.zeros((plane.shape[0] + 1, plane.shape[1] + 1), np.int64)
    total[1:, 1:] = plane.astype(np.int64).cumsum(0).cumsum(1)
    r2 = np.maximum(np.r_[rows[1:], plane.shape[0]], rows + 1)
    c2 = np.maximum(np.r_[cols[1:], plane.shape[1]], cols + 1)
    sums = total[np.ix_(r2, c2)] - total[np.ix_(rows, c2)] - total[np.ix_(r2, cols)] + total[np.ix_(rows, cols)]
    mean = sums / ((r2 - rows)[:, None] * (c2 - cols)[None, :])
    return np.packbits(mean[:, 1:] > mean[:, :-1]).tobytes().hex()


def features(data: bytes, planes: list[np.ndarray]) -> str:
    """Dimensions and thumbnail hash of each image, as text."""
    return ";".join(f"{s.width}x{s.height}:{thumbnail_hash(p)}" for s, p in zip(parse(data), planes, strict=True))


def media(texts: pa.Array):
    """For each text: its size, the payload read back from the stored stream, and that stream."""
    for slab in slabs(texts, 1 << 18):
        raw = slab.buf.tobytes()
        parts = [raw[a:b] for a, b in zip(slab.off[:-1].tolist(), slab.off[1:].tolist(), strict=True)]
        padded = [p + b"\xff" * ((-len(p)) % UNIT if p else UNIT) for p in parts]
        stored = store(padded)
        for p, d, planes in zip(parts, stored, dc_planes(stored), strict=True):
            yield len(p), b"".join(x.tobytes() for x in planes), d, planes


def digests(docs: DataFrame) -> DataFrame:
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]

    def work(batches):
        for b in batches:
            rows = [[] for _ in names[1:]]
            for n, payload, data, planes in media(b.column(1)):
                values = (n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(data), hashlib.sha256(data).hexdigest(), features(data, planes))
                for col, v in zip(rows, values, strict=True):
                    col.append(v)
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, t) for c, t in zip(rows, kinds, strict=True))], names)

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(work, schema)


def thumbnails(pictures: DataFrame, data: str = "data") -> DataFrame:
    """id columns beside ``data`` (binary) are kept; each baseline stream becomes width, height, thumbnail, hash.

    The new columns are _width, _height, _thumbnail and _hash, with more underscores before them where the table has such names already."""
    others = [c for c in pictures.columns if c != data]
    names = fresh(pictures, "_width", "_height", "_thumbnail", "_hash")

    def work(batches):
        for b in batches:
            blobs = b.column(len(others)).to_pylist()
            rows = []
            for blob in blobs:
                try:
                    s, p = parse(blob or b"")[:1], dc_planes([blob])[0] if blob else []
                    rows.append((s[0].width, s[0].height, p[0].tobytes(), thumbnail_hash(p[0])) if s else (None,) * 4)
                except (ValueError, IndexError, KeyError, struct.error):
                    rows.append((None,) * 4)
            kinds = [pa.int32(), pa.int32(), pa.binary(), pa.string()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(others)], *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], [*others, *names])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in pictures.schema if f.name != data), *(f"`{c}` {k}" for c, k in zip(names, ("int", "int", "binary", "string"), strict=True))])
    return pictures.select(*others, data).mapInArrow(work, schema)


def op6_jpeg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))
