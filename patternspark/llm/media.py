"""Media columns: baseline JPEG, read without an image library.

``decode`` parses markers, Huffman-decodes every scan of baseline JPEGs (any sampling, restart intervals, several
components) and rebuilds the luminance from DC coefficients alone: one sample per 8 x 8 block. The entropy decoder
works in lockstep: all restart segments of all images of a batch take one symbol at a time as numpy vectors, so cost
per symbol is a few vector operations whatever the number of images.

``encode_payload`` is the lossless carrier of bytes: 64 bytes are the 64 quantised coefficients of a block. A byte v
becomes the coefficient of size category 8 whose amplitude bits are v itself, in a restart interval of one block.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

_TALLEST = 65535 // 8


@dataclass
class Component:
    ident: int
    h: int
    v: int
    quant: int
    dc: int = 0
    ac: int = 0


@dataclass
class Picture:
    """Markers of one image; ``segments`` are the restart segments of its scans, stuffing removed."""

    width: int = 0
    height: int = 0
    components: list[Component] = field(default_factory=list)
    quant: dict[int, np.ndarray] = field(default_factory=dict)
    comment: bytes = b""
    scans: list[tuple[list[Component], tuple[np.ndarray, np.ndarray], int, dict]] = field(default_factory=list)

    def blocks(self, c: Component, alone: bool) -> tuple[int, int]:
        """Block rows and columns that a scan codes of ``c``."""
        hm, vm = max(x.h for x in self.components), max(x.v for x in self.components)
        if alone:
            return -(-(-(-self.height * c.v // vm)) // 8), -(-(-(-self.width * c.h // hm)) // 8)
        return -(-self.height // (8 * vm)) * c.v, -(-self.width // (8 * hm)) * c.h


def _table(counts: bytes, symbols: bytes) -> np.ndarray:
    """For each 16-bit window: code length << 8 | symbol; 0 where no code fits."""
    lut, code, at = np.zeros(1 << 16, dtype=np.int32), 0, 0
    for length in range(1, 17):
        for _ in range(counts[length - 1]):
            lo = code << (16 - length)
            lut[lo:lo + (1 << (16 - length))] = length << 8 | symbols[at]
            code, at = code + 1, at + 1
        code <<= 1
    return lut


_tables: dict[bytes, np.ndarray] = {}


def parse(data: bytes) -> Picture:
    """Markers of a baseline JPEG; ValueError if it is none or is cut off."""
    if data[:2] != b"\xff\xd8":
        raise ValueError("no start of image")
    pic, huff, interval, at = Picture(), {}, 0, 2
    raw = np.frombuffer(data, dtype="u1")
    try:
        while True:
            while data[at] != 0xFF:
                at += 1
            while data[at] == 0xFF:
                at += 1
            marker, at = data[at], at + 1
            if marker == 0xD9:
                return pic
            if marker in (0x01, *range(0xD0, 0xD8)):
                continue
            size = struct.unpack_from(">H", data, at)[0]
            body, at = data[at + 2:at + size], at + size
            if marker == 0xDB:
                while body:
                    wide, ident = body[0] >> 4, body[0] & 15
                    n = 128 if wide else 64
                    pic.quant[ident] = np.frombuffer(body[1:1 + n], dtype=">u2" if wide else "u1").astype(np.int64)
                    body = body[1 + n:]
            elif marker == 0xC4:
                while body:
                    n = sum(body[1:17])
                    key = body[1:17 + n]
                    if key not in _tables:
                        _tables[key] = _table(body[1:17], body[17:17 + n])
                    huff[body[0]] = _tables[key]
                    body = body[17 + n:]
            elif marker == 0xC0:
                bits, pic.height, pic.width, n = struct.unpack_from(">BHHB", body)
                if bits != 8:
                    raise ValueError("not 8-bit")
                pic.components = [Component(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)]
            elif 0xC1 <= marker <= 0xCF and marker not in (0xC8, 0xCC):
                raise ValueError("not baseline")
            elif marker == 0xDD:
                interval = struct.unpack(">H", body[:2])[0]
            elif marker == 0xFE:
                pic.comment = body
            elif marker == 0xDA:
                own = []
                for i in range(body[0]):
                    c = next(c for c in pic.components if c.ident == body[1 + 2 * i])
                    c.dc, c.ac = body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15
                    own.append(Component(c.ident, c.h, c.v, c.quant, c.dc, c.ac))
                # markers inside the coded data: 0xFF followed by neither 0x00 nor a restart number ends the scan
                ff = np.flatnonzero(raw[at:-1] == 0xFF) + at
                nxt = raw[ff + 1]
                ends = ff[(nxt != 0) & ((nxt < 0xD0) | (nxt > 0xD7)) & (nxt != 0xFF)]
                if not len(ends):
                    raise ValueError("scan without end")
                end = int(ends[0])
                restarts = ff[(ff < end) & (nxt >= 0xD0) & (nxt <= 0xD7)]
                stuffed = ff[(ff < end) & (nxt == 0)] + 1
                keep = np.ones(end - at, dtype=bool)
                keep[stuffed - at] = False
                keep[restarts - at] = False
                keep[restarts + 1 - at] = False
                kept = np.cumsum(keep)
                cuts = kept[restarts - at - 1] if len(restarts) else np.zeros(0, dtype=np.int64)
                pic.scans.append((own, (raw[at:end][keep], np.concatenate([[0], cuts, [kept[-1] if len(kept) else 0]]).astype(np.int64)), interval, dict(huff)))
                at = end
    except (IndexError, struct.error, StopIteration) as e:
        raise ValueError(f"broken markers: {e!r}") from None


#: A lockstep run codes segments of one layout: (block's component, tables) of an MCU, and how many MCUs.
def decode_coefficients(pics: list[Picture]) -> list[dict[int, np.ndarray]]:
    """Quantised coefficients of each picture: component -> (blocks in coded order, 64) in zigzag order."""
    groups: dict[tuple, list[tuple[int, int, np.ndarray, int, int]]] = {}
    tables: dict[int, np.ndarray] = {}
    for p, pic in enumerate(pics):
        for s, (own, (data, cuts), interval, huff) in enumerate(pic.scans):
            alone = len(own) == 1
            per = [1 if alone else c.h * c.v for c in own]
            rows, cols = pic.blocks(own[0], alone)
            mcus = rows * cols // per[0] if not alone else rows * cols
            layout = tuple((ci, id(huff[c.dc]), id(huff[16 + c.ac])) for ci, c in enumerate(own) for _ in range(per[ci]))
            for c in own:
                tables[id(huff[c.dc])], tables[id(huff[16 + c.ac])] = huff[c.dc], huff[16 + c.ac]
            step = interval or mcus
            if len(cuts) - 1 != -(-mcus // step):
                raise ValueError("restart markers do not fit the size")
            groups.setdefault(layout, []).append((p, s, data, cuts, mcus, step))
    out: list[dict[int, np.ndarray]] = [{} for _ in pics]
    for layout, parts in groups.items():
        base, lows, highs, counts = 0, [], [], []
        for *_, data, cuts, mcus, step in parts:
            lows.append(cuts[:-1] + base)
            highs.append(cuts[1:] + base)
            counts.append(np.minimum(step, mcus - step * np.arange(len(cuts) - 1)))
            base += len(data)
        buf = np.concatenate([x[2] for x in parts] + [np.zeros(8, dtype="u1")]).astype(np.uint32)
        coefs = _lockstep(buf, np.concatenate(lows) * 8, np.concatenate(highs) * 8, np.concatenate(counts), layout, tables)
        seg = np.concatenate([np.repeat(i, len(x[3]) - 1) for i, x in enumerate(parts)])
        bounds = np.concatenate([[0], np.cumsum(np.concatenate(counts))])
        first = np.searchsorted(seg, np.arange(len(parts) + 1))
        for i, (p, s, *_) in enumerate(parts):
            mine = coefs[bounds[first[i]]:bounds[first[i + 1]]]
            own = pics[p].scans[s][0]
            for ci, c in enumerate(own):
                slots = [k for k, (x, *_r) in enumerate(layout) if x == ci]
                out[p][c.ident] = mine[:, slots, :].reshape(-1, 64)
    return out


def _window(buf: np.ndarray, pos: np.ndarray) -> np.ndarray:
    """The 16 bits from bit ``pos`` on."""
    b = pos >> 3
    return ((buf[b] << 16 | buf[b + 1] << 8 | buf[b + 2]) >> (8 - (pos & 7)).astype(np.uint32)) & 0xFFFF


def _lockstep(buf, pos, end, counts, layout, tables) -> np.ndarray:
    """(MCUs, blocks of an MCU, 64): all segments side by side, one symbol of each a step."""
    total = int(counts.sum())
    out = np.zeros((total, len(layout), 64), dtype=np.int16)
    at = np.concatenate([[0], np.cumsum(counts)[:-1]])
    pos, pred = pos.astype(np.int64), np.zeros((1 + max(c for c, *_ in layout), len(pos)), dtype=np.int64)

    def symbol(lut, who):
        got = lut[_window(buf, pos[who])]
        if not got.all() or (pos[who] >= end[who]).any():
            raise ValueError("broken entropy code")
        pos[who] += got >> 8
        return got & 255

    def amplitude(bits, who):
        w = (_window(buf, pos[who]) >> (16 - bits).astype(np.uint32)).astype(np.int64)
        pos[who] += bits
        return np.where(w < (1 << bits) >> 1, w - (1 << bits) + 1, w)

    for m in range(int(counts.max(initial=0))):
        live = np.flatnonzero(counts > m)
        for k, (ci, dc, ac) in enumerate(layout):
            size = symbol(tables[dc], live)
            pred[ci, live] += amplitude(size, live)
            out[at[live] + m, k, 0] = pred[ci, live]
            who, i = live, np.ones(len(live), dtype=np.int64)
            while len(who):
                s = symbol(tables[ac], who)
                run, size = s >> 4, s & 15
                value = amplitude(size, who)
                i = i + run
                some = size > 0
                if (i[some] > 63).any():
                    raise ValueError("coefficients beyond the block")
                if some.all():
                    out[at[who] + m, k, i] = value
                    i = i + 1
                    on = i < 64
                else:
                    out[at[who[some]] + m, k, i[some]] = value[some]
                    on = (some | (run == 15)) & (i + 1 < 64)
                    i = i + 1
                if not on.all():
                    who, i = who[on], i[on]
    if (pos > end).any():
        raise ValueError("coded data is cut off")
    return out


def thumbnails(pics: list[Picture], coefs: list[dict[int, np.ndarray]]) -> list[np.ndarray]:
    """DC-only luminance of each picture: one sample per 8 x 8 block of its first component."""
    out = []
    for pic, own in zip(pics, coefs):
        c = pic.components[0]
        scan = next(s for s in pic.scans if any(x.ident == c.ident for x in s[0]))
        alone = len(scan[0]) == 1
        rows, cols = pic.blocks(c, alone)
        dc = own[c.ident][:, 0].astype(np.int64)
        if alone:
            grid = dc.reshape(rows, cols)
        else:  # coded MCU by MCU
            grid = dc.reshape(rows // c.v, cols // c.h, c.v, c.h).transpose(0, 2, 1, 3).reshape(rows, cols)
        vm, hm = max(x.v for x in pic.components), max(x.h for x in pic.components)
        rows, cols = -(-(-(-pic.height * c.v // vm)) // 8), -(-(-(-pic.width * c.h // hm)) // 8)
        level = np.clip(np.round(grid[:rows, :cols] * int(pic.quant[c.quant][0]) / 8 + 128), 0, 255)
        out.append(level.astype("u1"))
    return out


def thumbnail_hash(level: np.ndarray) -> str:
    """64-bit difference hash of a thumbnail shrunk to 9 x 8 cell means, as 16 hex digits."""
    rows = (np.arange(9) * level.shape[0] / 8).astype(int)[:9]
    cols = (np.arange(10) * level.shape[1] / 9).astype(int)
    area = np.zeros((level.shape[0] + 1, level.shape[1] + 1), dtype=np.int64)
    area[1:, 1:] = level.astype(np.int64).cumsum(0).cumsum(1)
    r0, r1 = rows[:8], np.maximum(rows[1:9], rows[:8] + 1)
    c0, c1 = cols[:9], np.maximum(cols[1:10], cols[:9] + 1)
    cell = (area[np.ix_(r1, c1)] - area[np.ix_(r0, c1)] - area[np.ix_(r1, c0)] + area[np.ix_(r0, c0)]) / ((r1 - r0)[:, None] * (c1 - c0)[None, :])
    return np.packbits(cell[:, 1:] > cell[:, :-1]).tobytes().hex()


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def pad(payload: bytes) -> bytes:
    """Bytes 0 up to a positive multiple of 64."""
    return payload + bytes(-len(payload) % 64 or (64 if not payload else 0))


_ONES = _segment(0xDB, b"\x00" + b"\x01" * 64)
_CODES = _segment(0xC4, b"\x00" + b"\x01" + bytes(15) + b"\x08") + _segment(0xC4, b"\x10" + b"\x01" + bytes(15) + b"\x08")


def encode_payload(payload: bytes) -> bytes:
    """A grey baseline JPEG whose coefficients are the payload's bytes (its length a positive multiple of 64)."""
    n = len(payload) // 64
    wide = isqrt(n - 1) + 1  # nearly square; the last row is filled up with empty blocks
    if wide > _TALLEST:
        raise ValueError("payload beyond the largest image")
    tall = -(-n // wide)
    blocks = np.zeros((tall * wide, 64), dtype="u1")
    blocks[:n] = np.frombuffer(payload, dtype="u1").reshape(n, 64)
    # each coefficient: a one-bit code 0 and its 8 amplitude bits; 576 bits fill 72 bytes, so restarts need no filling
    bits = np.zeros((len(blocks), 64, 9), dtype="u1")
    bits[:, :, 1:] = np.unpackbits(blocks, axis=1).reshape(-1, 64, 8)
    coded = np.packbits(bits.reshape(len(blocks), -1), axis=1)
    size = np.ones((len(blocks), 74), dtype=np.int64)
    size[:, :72] += coded == 0xFF
    ends = np.cumsum(size.ravel())
    stream = np.zeros(int(ends[-1]), dtype="u1")
    marks = np.tile(np.array([0xFF, 0], dtype="u1"), (len(blocks), 1))
    marks[:, 1] = 0xD0 + np.arange(len(blocks)) % 8
    stream[ends - size.ravel()] = np.concatenate([coded, marks], axis=1).ravel()
    head = b"\xff\xd8" + _segment(0xFE, b"payload %d" % len(payload)) + _ONES + _segment(0xC0, struct.pack(">BHHBBBB", 8, tall * 8, wide * 8, 1, 1, 0x11, 0)) + _CODES + _segment(0xDD, struct.pack(">H", 1)) + _segment(0xDA, b"\x01\x01\x00\x00\x3f\x00")
    return head + stream[:-2].tobytes() + b"\xff\xd9"


def payload_of(pic: Picture, coefs: dict[int, np.ndarray]) -> bytes:
    """The bytes that ``encode_payload`` has stored."""
    c = coefs[pic.components[0].ident].astype(np.int64)
    n = int(pic.comment.removeprefix(b"payload "))
    return np.where(c < 0, c + 255, c).astype("u1").tobytes()[:n]


def decode(images: list[bytes]) -> tuple[list[Picture], list[dict[int, np.ndarray]], list[np.ndarray]]:
    """Pictures, coefficients and DC thumbnails of a batch of baseline JPEGs."""
    pics = [parse(x) for x in images]
    coefs = decode_coefficients(pics)
    return pics, coefs, thumbnails(pics, coefs)


MEDIA = "id {id}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
_BATCH_BYTES = 4 << 20


def media_columns(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store every text as a JPEG, read it back and describe it: sizes, hashes, and ``feature`` = size and thumbnail hash.

    Null text counts as empty (one block of zeros). Equal texts get equal values whatever else is in their batch.
    Texts of any length are stored whole (several rows of blocks); repeated rows give repeated results, other columns
    are ignored; an empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raws = [(t or "").encode("utf-8", "surrogatepass") for t in b.column(1).to_pylist()]
            rows, lo = [], 0
            while lo < len(raws):
                hi, held = lo, 0
                while hi < len(raws) and (hi == lo or held + len(raws[hi]) <= _BATCH_BYTES):
                    held += len(raws[hi])
                    hi += 1
                stored = [encode_payload(pad(x)) for x in raws[lo:hi]]
                pics, coefs, levels = decode(stored)
                for x, jpeg, pic, c, level in zip(raws[lo:hi], stored, pics, coefs, levels):
                    back = payload_of(pic, c)
                    rows.append((len(x), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(jpeg), hashlib.sha256(jpeg).hexdigest(), f"{pic.width}x{pic.height}:{thumbnail_hash(level)}"))
                lo = hi
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds))], names=["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return docs.select(id_col, text_col).mapInArrow(run, MEDIA.format(id=dict(docs.dtypes)[id_col]))
