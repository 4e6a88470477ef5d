"""Media columns: bytes kept losslessly in progressive JPEGs, and a decoder of progressive JPEGs to RGB tensors.

A payload byte is one quantised coefficient, so the file's unit is the coefficient: byte 0 of each 64 is the DC value, the
others are AC values of magnitude 128 to 255, with the byte's upper seven bits coded in a first scan at bit position 1 and its lowest
bit in a refinement scan. Two spectral bands at first, one when refined, nine successive DC scans (one bit each after the first), 4:2:0 sampling and
tables of ones for quantisation. The length before padding to whole MCUs stands in a comment segment.

The decoder takes any progressive (or sequential Huffman) 8-bit JPEG of one or three components: scans accumulate into coefficient arrays, then
come the inverse transform, chroma upsampling and conversion in numpy. Scans in which every symbol has one width, as those
written here, are read as arrays; others symbol by symbol. The inverse transform has whole-number weights, exact in
doubles, so equal files give equal tensors anywhere.

Results for odd input: a null or empty text is 192 blanks; repeated rows repeat; an empty table gives no row; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import byte_view, mapped, materialise

UNIT = 192
MCU = 384
WIDE = 64
#: MCUs of a column at most, as the format has 16 bits for a height: higher pictures grow wide instead.
HIGH = 4095
BANDS = ((1, 5), (6, 63))
DC_BITS = 8


def zigzag() -> np.ndarray:
    """Place in the 8 x 8 block of each coefficient in scan order: along anti-diagonals, up and down in turn."""
    cells = [(i, j) for i in range(8) for j in range(8)]
    cells.sort(key=lambda c: (sum(c), c[0] if sum(c) % 2 else c[1]))
    return np.array([8 * i + j for i, j in cells])


ORDER = zigzag()
#: The end of a scan: a marker other than a restart; and restarts.
MARKER, RESTART = re.compile(rb"\xff[^\x00\xd0-\xd7]"), re.compile(rb"\xff[\xd0-\xd7]")
#: Weights of the inverse transform times 2^10, as whole numbers.
BASIS = np.round(1024 * np.array([[(np.sqrt(0.125) if u == 0 else 0.5) * np.cos((2 * x + 1) * u * np.pi / 16) for x in range(8)] for u in range(8)]))


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _table(kind: int, number: int, by_length: dict[int, list[int]]) -> bytes:
    return _segment(0xC4, bytes([kind << 4 | number]) + bytes(len(by_length.get(n, [])) for n in range(1, 17)) + bytes(s for n in sorted(by_length) for s in by_length[n]))


def _scan(parts: list[tuple[int, int]], ss: int, se: int, ah: int, al: int, coded: bytes) -> bytes:
    head = bytes([len(parts)]) + b"".join(bytes(p) for p in parts) + bytes([ss, se, ah << 4 | al])
    return _segment(0xDA, head) + coded


def _packed(bits: np.ndarray) -> bytes:
    """Bits as bytes, the last filled up with ones, 255 followed by 0."""
    fill = -len(bits) % 8
    raw = np.packbits(np.concatenate([bits, np.ones(fill, np.uint8)]) if fill else bits).tobytes()
    return raw.replace(b"\xff", b"\xff\x00")


#: DC differences are all zero, AC values all of seven bits after no zeros, ends of bands of any run: one code length each.
TABLES = _table(0, 0, {1: [0]}) + _table(1, 0, {1: [7]}) + _table(1, 1, {4: [16 * n for n in range(15)]})
RUN_BLOCKS = 32767


def pad(raw: bytes) -> bytes:
    return raw + b" " * (UNIT if not raw else -len(raw) % UNIT)


def encode(payload: bytes) -> bytes:
    """A progressive JPEG whose coefficients are the payload's bytes."""
    mcus = -(-len(payload) // MCU)
    high = -(-mcus // max(WIDE, -(-mcus // HIGH)))
    wide = -(-mcus // high)
    n = wide * high
    data = np.zeros(n * MCU, np.uint8)
    data[: len(payload)] = np.frombuffer(payload, np.uint8)
    block = data.reshape(-1, 64)
    planes = (block[: 4 * n], block[4 * n : 5 * n], block[5 * n :])
    out = [b"\xff\xd8", _segment(0xFE, struct.pack(">Q", len(payload))), _segment(0xDB, b"\0" + b"\1" * 64), _segment(0xC2, struct.pack(">BHHB", 8, 16 * high, 16 * wide, 3) + bytes([1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])), TABLES]
    every = [(1, 0), (2, 0), (3, 0)]
    dc = np.empty((n, 6), np.uint8)
    dc[:, :4] = planes[0][:, 0].reshape(high, 2, wide, 2).transpose(0, 2, 1, 3).reshape(n, 4)
    dc[:, 4], dc[:, 5] = planes[1][:, 0], planes[2][:, 0]
    out.append(_scan(every, 0, 0, 0, DC_BITS, _packed(np.zeros(6 * n, np.uint8))))
    bits = np.unpackbits(dc.reshape(-1, 1), axis=1)
    for k in range(DC_BITS):
        out.append(_scan(every, 0, 0, DC_BITS - k, DC_BITS - k - 1, _packed(bits[:, k])))
    for c, plane in enumerate(planes, 1):
        for a, b in BANDS:
            out.append(_scan([(c, 0x00)], a, b, 0, 1, (plane[:, a : b + 1] >> 1).tobytes()))
    for c, plane in enumerate(planes, 1):
        low = plane[:, 1:] & 1
        parts = []
        for k in range(0, len(plane), RUN_BLOCKS):
            run = min(RUN_BLOCKS, len(plane) - k)
            size = run.bit_length() - 1
            head = f"{size:04b}" + (f"{run - (1 << size):0{size}b}" if size else "")
            parts += [np.frombuffer(head.encode(), np.uint8) - 48, low[k : k + run].reshape(-1)]
        out.append(_scan([(c, 0x01)], 1, 63, 1, 0, _packed(np.concatenate(parts))))
    return b"".join([*out, b"\xff\xd9"])


# ---- decoding ----------------------------------------------------------------------------------------------------

class Huffman:
    def __init__(self, counts: bytes, symbols: bytes):
        self.codes, code, k = {}, 0, 0
        for length, many in enumerate(counts, 1):
            for _ in range(many):
                self.codes[length, code] = symbols[k]
                code, k = code + 1, k + 1
            code <<= 1
        self.only = next(iter(self.codes.items())) if len(self.codes) == 1 else None


class Bits:
    """Reads a scan's bits one by one."""

    def __init__(self, raw: bytes):
        self.bit = np.unpackbits(np.frombuffer(raw, np.uint8))
        self.at = 0

    def take(self, n: int) -> int:
        out = 0
        for _ in range(n):
            out = out << 1 | (int(self.bit[self.at]) if self.at < len(self.bit) else 0)
            self.at += 1
        return out

    def symbol(self, table: Huffman) -> int:
        code, length = 0, 0
        while length < 16:
            code, length = code << 1 | self.take(1), length + 1
            if (length, code) in table.codes:
                return table.codes[length, code]
        raise ValueError("not a code of the table")

    def signed(self, size: int) -> int:
        value = self.take(size)
        return value if not size or value >> (size - 1) else value - (1 << size) + 1


class Component:
    def __init__(self, h: int, v: int, quant: int):
        self.h, self.v, self.quant = h, v, quant


def _blocks_of(image: dict, parts: list[Component]) -> dict:
    """Block numbers in the order that a scan of these components has them: of each component by unit, and of all in the common array."""
    if len(parts) == 1:
        c = parts[0]
        line = range(c.rows * c.cols) if c.cols == c.stride else (np.arange(c.rows)[:, None] * c.stride + np.arange(c.cols)).reshape(-1)
        each = [np.asarray(line).reshape(-1, 1)]
    else:
        line, each = None, []
        for c in parts:
            y, x = np.arange(image["mcu_rows"] * c.v), np.arange(image["mcu_cols"] * c.h)
            grid = (y[:, None] * c.stride + x).reshape(image["mcu_rows"], c.v, image["mcu_cols"], c.h)
            each.append(grid.transpose(0, 2, 1, 3).reshape(-1, c.v * c.h))
    return {"line": line, "each": each, "all": np.concatenate([o + c.base for c, o in zip(parts, each, strict=True)], axis=1)}


def _rows(blocks):
    """Blocks as a slice where they follow one another."""
    return slice(blocks.start, blocks.stop) if isinstance(blocks, range) else blocks


def _dc_scan(bits_of, image, parts, order, tables, ah, al, fast) -> None:
    where, units = order["all"], len(order["all"])
    if ah:
        got = [np.unpackbits(np.frombuffer(raw, np.uint8), count=where.shape[1] * n) for raw, n in bits_of(units)]
        bit = (got[0] if len(got) == 1 else np.concatenate(got)).reshape(where.shape)
        image["coef"][where, 0] += bit.astype(np.int32) << al
        return
    first = 0
    for raw, n in bits_of(units):
        if fast and all(t.only and t.only[1] == 0 for t in tables):
            first += n
            continue
        bits, last = Bits(raw), [0] * len(parts)
        for unit in range(first, first + n):
            for k, o in enumerate(order["each"]):
                for block in o[unit]:
                    last[k] += bits.signed(bits.symbol(tables[k]))
                    parts[k].coef[block, 0] = last[k] * (1 << al)
        first += n


def _ac_first(raw, c, blocks, table, ss, se, al, fast) -> None:
    wide = se - ss + 1
    if fast and table.only and table.only[1] >> 4 == 0 and table.only[1] & 15:
        (length, _), size = table.only
        step = length + size
        if step == 8:
            field = np.frombuffer(raw, np.uint8)[: len(blocks) * wide].astype(np.int32)
        else:
            bit = np.unpackbits(np.frombuffer(raw, np.uint8))[: len(blocks) * wide * step].reshape(-1, step)
            field = bit.astype(np.int32) @ (1 << np.arange(step - 1, -1, -1, dtype=np.int32))
        value = field & ((1 << size) - 1)
        value = np.where(value >> (size - 1), value, value - (1 << size) + 1) << al
        c.coef[_rows(blocks), ss : se + 1] = value.reshape(-1, wide)
        return
    bits, run = Bits(raw), 0
    for block in blocks:
        if run:
            run -= 1
            continue
        k = ss
        while k <= se:
            symbol = bits.symbol(table)
            zeros, size = symbol >> 4, symbol & 15
            if size:
                k += zeros
                value = bits.signed(size)
                c.coef[block, k] = value * (1 << al)
                k += 1
            elif zeros == 15:
                k += 16
            else:
                run = (1 << zeros) + bits.take(zeros) - 1
                break


def _ac_refine(raw, c, blocks, table, ss, se, al, fast) -> None:
    one = 1 << al
    band = c.coef[_rows(blocks), ss : se + 1]
    lengths = {n for n, _ in table.codes}
    if fast and len(lengths) == 1 and not any(s & 15 for s in table.codes.values()) and band.all():
        bit, at, done, (length,) = np.unpackbits(np.frombuffer(raw, np.uint8)), 0, 0, lengths
        take = lambda a, n: int.from_bytes(np.packbits(bit[a : a + n]).tobytes()) >> (-n % 8)
        while done < len(blocks):
            size = table.codes[length, take(at, length)] >> 4
            run = (1 << size) + take(at + length, size)
            at += length + size
            own = bit[at : at + run * band.shape[1]].reshape(-1, band.shape[1]).astype(np.int32) << al
            at += own.size
            part = band[done : done + run]
            part += own * ((part > 0) * 2 - 1)
            done += run
        c.coef[_rows(blocks), ss : se + 1] = band
        return
    bits, run = Bits(raw), 0

    def more(block, k):
        if bits.take(1):
            c.coef[block, k] += one if c.coef[block, k] > 0 else -one

    for block in blocks:
        k = ss
        if not run:
            while k <= se:
                symbol = bits.symbol(table)
                zeros, size = symbol >> 4, symbol & 15
                new = 0
                if size:
                    new = one if bits.take(1) else -one
                elif zeros < 15:
                    run = (1 << zeros) + bits.take(zeros)
                    break
                while k <= se:
                    if c.coef[block, k]:
                        more(block, k)
                    elif zeros == 0:
                        if new:
                            c.coef[block, k] = new
                        k += 1
                        break
                    else:
                        zeros -= 1
                    k += 1
        if run:
            for j in range(k, se + 1):
                if c.coef[block, j]:
                    more(block, j)
            run -= 1


def decode(raw: bytes, fast: bool = True) -> dict:
    """Coefficient arrays (in scan order) and what else the file tells: comment, size, components, quantisation tables."""
    image: dict = {"comment": b"", "components": {}, "quant": {}}
    huff: dict[tuple[int, int], Huffman] = {}
    orders: dict[bytes, list] = {}
    at, restart = 2, 0
    if raw[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG")
    while True:
        marker, (size,) = raw[at + 1], struct.unpack_from(">H", raw, at + 2) if raw[at + 1] != 0xD9 else (0,)
        body = raw[at + 4 : at + 2 + size]
        if raw[at] != 0xFF:
            raise ValueError("a marker is missing")
        if marker == 0xD9:
            return image
        at += 2 + size
        if marker == 0xFE:
            image["comment"] = body
        elif marker == 0xDB:
            while body:
                wide = body[0] >> 4
                image["quant"][body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else np.uint8).astype(np.int64)
                body = body[65 + 64 * wide :]
        elif marker == 0xC4:
            while body:
                many = sum(body[1:17])
                huff[body[0] >> 4, body[0] & 15] = Huffman(body[1:17], body[17 : 17 + many])
                body = body[17 + many :]
        elif marker == 0xDD:
            (restart,) = struct.unpack(">H", body)
        elif marker in (0xC0, 0xC1, 0xC2):
            _, high, wide, n = struct.unpack_from(">BHHB", body)
            image |= {"height": high, "width": wide, "progressive": marker == 0xC2}
            parts = {body[6 + 3 * k]: Component(body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k]) for k in range(n)}
            h, v = max(c.h for c in parts.values()), max(c.v for c in parts.values())
            image |= {"components": parts, "h": h, "v": v, "mcu_cols": -(-wide // (8 * h)), "mcu_rows": -(-high // (8 * v))}
            for c in parts.values():
                c.cols, c.rows = -(-(-(-wide * c.h // h)) // 8), -(-(-(-high * c.v // v)) // 8)
                c.stride = image["mcu_cols"] * c.h
                c.base = sum(x.size for x in parts.values() if hasattr(x, "size"))
                c.size = c.stride * image["mcu_rows"] * c.v
            image["coef"] = np.zeros((sum(c.size for c in parts.values()), 64), np.int32)
            for c in parts.values():
                c.coef = image["coef"][c.base : c.base + c.size]
        elif marker == 0xDA:
            n = body[0]
            own = [(image["components"][body[1 + 2 * k]], body[2 + 2 * k]) for k in range(n)]
            ss, se, ah, al = body[1 + 2 * n], body[2 + 2 * n], body[3 + 2 * n] >> 4, body[3 + 2 * n] & 15
            stop = MARKER.search(raw, at).start()
            pieces = [p.replace(b"\xff\x00", b"\xff") for p in RESTART.split(raw[at:stop])] if restart else [raw[at:stop].replace(b"\xff\x00", b"\xff")]
            at = stop

            def cut(units: int, pieces=pieces):
                every = restart or units
                return [(p, min(every, units - k * every)) for k, p in enumerate(pieces)]

            parts = [c for c, _ in own]
            order = orders.get(names := bytes(body[1 : 1 + 2 * n : 2])) or orders.setdefault(names, _blocks_of(image, parts))
            if not image["progressive"]:
                _sequential(cut, own, order["each"], huff)
            elif ss == 0:
                _dc_scan(cut, image, parts, order, [huff.get((0, t >> 4)) for _, t in own], ah, al, fast)
            else:
                c, t = own[0]
                first = 0
                for piece, many in cut(len(order["line"])):
                    (_ac_refine if ah else _ac_first)(piece, c, order["line"][first : first + many], huff[1, t & 15], ss, se, al, fast)
                    first += many
        elif 0xC3 <= marker <= 0xCF:
            raise ValueError("a kind of JPEG that is not read here")


def _sequential(cut, own, where, huff) -> None:

    first = 0
    for raw, n in cut(len(where[0])):
        bits, last = Bits(raw), [0] * len(own)
        for unit in range(first, first + n):
            for k, ((c, t), o) in enumerate(zip(own, where, strict=True)):
                for block in o[unit]:
                    last[k] += bits.signed(bits.symbol(huff[0, t >> 4]))
                    c.coef[block, 0] = last[k]
                    at = 1
                    while at < 64:
                        symbol = bits.symbol(huff[1, t & 15])
                        if symbol == 0:
                            break
                        at += symbol >> 4
                        if symbol & 15:
                            c.coef[block, at] = bits.signed(symbol & 15)
                        at += 1
        first += n


def to_rgb(image: dict) -> np.ndarray:
    """The full-resolution RGB tensor, height x width x 3."""
    planes = []
    for c in image["components"].values():
        flat = np.zeros((len(c.coef), 64))
        flat[:, ORDER] = c.coef * image["quant"][c.quant]
        half = (flat.reshape(-1, 8) @ BASIS).reshape(-1, 8, 8).transpose(0, 2, 1).reshape(-1, 8) @ BASIS
        value = np.floor((half + (1 << 19)) * 2.0**-20).reshape(-1, 8, 8).transpose(0, 2, 1)
        value = np.clip(value + 128, 0, 255).astype(np.int32)
        plane = value.reshape(-1, c.stride, 8, 8).transpose(0, 2, 1, 3).reshape(-1, 8 * c.stride)
        if (down := image["v"] // c.v) > 1:
            plane = np.repeat(plane, down, 0)
        if (across := image["h"] // c.h) > 1:
            plane = np.repeat(plane, across, 1)
        planes.append(plane[: image["height"], : image["width"]])
    if len(planes) == 1:
        return np.repeat(planes[0][:, :, None], 3, 2).astype(np.uint8)
    y, b, r = planes[0], planes[1] - 128, planes[2] - 128
    # 1.402, 0.344136, 0.714136 and 1.772, times 2^16: fixed values of the colour space.
    rgb = np.empty((*y.shape, 3), np.uint8)
    rgb[..., 0] = np.clip(y + ((91881 * r + 32768) >> 16), 0, 255)
    rgb[..., 1] = np.clip(y - ((22554 * b + 46802 * r + 32768) >> 16), 0, 255)
    rgb[..., 2] = np.clip(y + ((116130 * b + 32768) >> 16), 0, 255)
    return rgb


def payload_of(image: dict) -> bytes:
    """The bytes that encode() was given."""
    (n,) = struct.unpack(">Q", image["comment"])
    coef = image["coef"]
    size, sign = np.abs(coef), coef > 0
    out = np.where(sign, size, ((127 - (size >> 1)) << 1) | (size & 1))
    out[:, 0] = coef[:, 0]
    return out.astype(np.uint8).reshape(-1)[:n].tobytes()


def feature(rgb: np.ndarray) -> str:
    """Size, channel means (rounded down) and CRC of a tensor."""
    mean = rgb.reshape(-1, 3).sum(0, dtype=np.int64) // max(1, rgb.shape[0] * rgb.shape[1])
    return f"{rgb.shape[1]}x{rgb.shape[0]}:{','.join(map(str, mean.tolist()))}:{zlib.crc32(rgb.tobytes()):08x}"


def store(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media (the JPEG) of every text."""

    def run(batches):
        for batch in batches:
            data, at = byte_view(batch.column(1))
            raw = data.tobytes()
            for k in range(0, batch.num_rows, 512):
                own = [raw[at[i] : at[i + 1]] for i in range(k, min(k + 512, batch.num_rows))]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(k, len(own)), pa.array([len(x) for x in own], pa.int64()), pa.array([encode(pad(x)) for x in own], pa.binary())], names=["doc_id", "n_bytes", "media"])

    return mapped(docs.select("doc_id", "text"), run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_bytes bigint, media binary")


def tensors(media: DataFrame, column: str = "media") -> DataFrame:
    """The other columns, with height, width and rgb (bytes, row by row) of each JPEG."""
    rest = [f for f in media.schema if f.name != column]

    def run(batches):
        for batch in batches:
            k = batch.schema.names.index(column)
            for i in range(batch.num_rows):
                rgb = to_rgb(decode(batch.column(k)[i].as_py()))
                yield pa.RecordBatch.from_arrays([*(batch.column(j).slice(i, 1) for j in range(batch.num_columns) if j != k), pa.array([rgb.shape[0]]), pa.array([rgb.shape[1]]), pa.array([rgb.tobytes()], pa.binary())], names=[*(n for n in batch.schema.names if n != column), "height", "width", "rgb"])

    return mapped(media, run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rest), "height bigint, width bigint, rgb binary"]))


def report(media: DataFrame) -> DataFrame:
    """Digests of the payload read back, of the file and of its tensor."""
    kinds = {"n_bytes": pa.int64(), "payload_bytes": pa.int64(), "payload_sha256": pa.string(), "tail_crc32": pa.int64(), "media_bytes": pa.int64(), "media_sha256": pa.string(), "feature": pa.string()}

    def run(batches):
        for batch in batches:
            rows = []
            for n, raw in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                raw = raw.as_py()
                image = decode(raw)
                payload = payload_of(image)
                rows.append((n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(raw), hashlib.sha256(raw).hexdigest(), feature(to_rgb(image))))
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds.values()))], names=["doc_id", *kinds])

    kind = media.schema["doc_id"].dataType.simpleString()
    return mapped(media.select("doc_id", "n_bytes", "media"), run, f"doc_id {kind}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")


def stored_and_read(docs: DataFrame) -> DataFrame:
    """Store every text, read the stored files back and report on them."""
    return report(materialise(store(docs)))
