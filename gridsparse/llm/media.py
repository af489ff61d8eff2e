"""Baseline JPEG columns: reading, DC-only thumbnails, lossless payloads, and op3.

The reader parses markers, undoes byte stuffing, and Huffman-decodes the scan
of any number of files at once: every restart interval (or a whole scan where
there is none) is one lane, and all lanes advance by one symbol per numpy
step.  Thumbnails take the DC coefficient of each luminance block.

A payload is stored in the format's own unit: 64 bytes are the 64 quantised
coefficients of one 8x8 block, each byte less 128, under a unit quantisation
table, with a restart interval of one block; so reading gives the bytes back
exactly.  The payload's length stands in a comment segment, since blocks fill a
rectangle.

Null and empty texts are the 64 zero bytes; texts up to 4 GB fit the format's
dimensions.
"""

from __future__ import annotations

import hashlib
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from gridsparse.llm import common

BLOCK = 64
LEVEL = 128
CHUNK = 1 << 15  # blocks that are coded at once
#: Magnitude bits of a coefficient by its absolute value.
CATEGORY = np.array([int(v).bit_length() for v in range(2048)], np.int64)


# -- Huffman tables ------------------------------------------------------------
@dataclass
class Huffman:
    """A table as the format transmits it (counts per length, values), with code and decoding arrays."""

    counts: list[int]
    values: list[int]
    code: np.ndarray = field(init=False)
    length: np.ndarray = field(init=False)
    look: np.ndarray = field(init=False)

    def __post_init__(self):
        self.code, self.length = np.zeros(256, np.int64), np.zeros(256, np.int64)
        self.look = np.zeros(1 << 16, np.int64)  # symbol * 32 + length for each 16-bit window, 0 if no code
        code, at = 0, 0
        for bits in range(1, 17):
            for _ in range(self.counts[bits - 1]):
                value = self.values[at]
                self.code[value], self.length[value] = code, bits
                low = code << (16 - bits)
                self.look[low : low + (1 << (16 - bits))] = value * 32 + bits
                code, at = code + 1, at + 1
            code <<= 1

    @property
    def segment(self) -> bytes:
        return bytes(self.counts) + bytes(self.values)


def _table(lengths: dict[int, int]) -> Huffman:
    counts = [sum(v == n for v in lengths.values()) for n in range(1, 17)]
    return Huffman(counts, sorted(lengths, key=lambda s: (lengths[s], s)))


#: Our own tables, made for text bytes less 128: DC differences of up to 8 bits, AC symbols run * 16 + size.
DC_TABLE = _table({size: 4 for size in range(9)})
AC_TABLE = _table({5: 2, 6: 3, 4: 3, 7: 3, 3: 4, 2: 6, 8: 6, 1: 6, 0x00: 6, 0xF0: 12} | {run * 16 + size: 13 for run in range(1, 16) for size in range(1, 9)})


# -- writing -------------------------------------------------------------------
def _layout(blocks: int) -> tuple[int, int]:
    """Blocks per row and rows of the rectangle."""
    wide = max(1, int(np.ceil(np.sqrt(blocks))))
    return wide, -(-blocks // wide)


def _segment(marker: int, body: bytes) -> bytes:
    return bytes((0xFF, marker)) + (len(body) + 2).to_bytes(2, "big") + body


def encode_blocks(coefficients: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entropy-code blocks (n x 64, zigzag order), each alone: stuffed bytes of all, and each one's length."""
    n = len(coefficients)
    width = 64 * 4 + 8
    out = np.zeros((n, width), np.uint8)
    used = np.zeros(n, np.int64)
    run = np.zeros(n, np.int64)
    every = np.arange(n)

    def put(rows, code, size):
        """Append ``size`` (at most 24) bits of ``code`` for the rows."""
        at = used[rows]
        word = code << (32 - size - (at & 7))
        byte = at >> 3
        for k in range(4):
            out[rows, byte + k] |= ((word >> (24 - 8 * k)) & 255).astype(np.uint8)
        used[rows] = at + size

    def magnitude(values):
        size = CATEGORY[np.abs(values)]
        return size, np.where(values < 0, values + (1 << size) - 1, values)

    size, bits = magnitude(coefficients[:, 0].astype(np.int64))
    put(every, (DC_TABLE.code[size] << size) | bits, DC_TABLE.length[size] + size)
    for k in range(1, 64):
        value = coefficients[:, k].astype(np.int64)
        some = np.flatnonzero(value)
        run += value == 0
        while len(long := some[run[some] > 15]):
            put(long, np.broadcast_to(AC_TABLE.code[0xF0], len(long)), np.broadcast_to(AC_TABLE.length[0xF0], len(long)))
            run[long] -= 16
        if len(some) == n:
            some = every
        size, bits = magnitude(value[some])
        symbol = run[some] * 16 + size
        put(some, (AC_TABLE.code[symbol] << size) | bits, AC_TABLE.length[symbol] + size)
        run[some] = 0
    short = np.flatnonzero(run)
    put(short, np.broadcast_to(AC_TABLE.code[0], len(short)), np.broadcast_to(AC_TABLE.length[0], len(short)))
    pad = -used & 7
    put(every, (1 << pad) - 1, pad)
    lengths = used >> 3
    flat = out[np.arange(width)[None, :] < lengths[:, None]]
    full = flat == 255
    owner = np.repeat(every, lengths)
    lengths = lengths + np.bincount(owner[full], minlength=n)
    stuffed = np.zeros(len(flat) + int(full.sum()), np.uint8)
    stuffed[np.arange(len(flat)) + np.cumsum(full) - full] = flat
    return stuffed, lengths


HEAD = b"\xff\xd8"
TABLES = _segment(0xDB, b"\x00" + b"\x01" * 64) + _segment(0xC4, b"\x00" + DC_TABLE.segment) + _segment(0xC4, b"\x10" + AC_TABLE.segment) + _segment(0xDD, b"\x00\x01")
SCAN = _segment(0xDA, b"\x01\x01\x00\x00\x3f\x00")


def pack(payloads: list[bytes]) -> list[bytes]:
    """A JPEG file for each payload (a positive multiple of 64 bytes)."""
    shapes = [(len(p) // BLOCK, *_layout(len(p) // BLOCK)) for p in payloads]
    fill = bytes([LEVEL]) * BLOCK
    raw = b"".join(p + fill * (w * h - n) for p, (n, w, h) in zip(payloads, shapes, strict=True))
    coefficients = np.frombuffer(raw, np.uint8).reshape(-1, 64).astype(np.int16) - LEVEL
    parts = [encode_blocks(coefficients[a : a + CHUNK]) for a in range(0, max(1, len(coefficients)), CHUNK)]
    coded, lengths = (np.concatenate(x) for x in zip(*parts, strict=True))
    files, block, at = [], 0, 0
    # each block's bytes are followed by a restart marker, except a scan's last
    sizes = [w * h for _, w, h in shapes]
    number = np.concatenate([np.arange(s) for s in sizes]) if sizes else np.empty(0, np.int64)
    spread = np.zeros(len(coded) + 2 * len(lengths), np.uint8)
    ends = np.cumsum(lengths) + 2 * np.arange(len(lengths))
    spread[ends], spread[ends + 1] = 0xFF, 0xD0 + number % 8
    body = np.ones(len(spread), bool)
    body[ends] = body[ends + 1] = False
    spread[body] = coded
    for payload, (_, w, h) in zip(payloads, shapes, strict=True):
        last = block + w * h - 1
        frame = b"\x08" + (8 * h).to_bytes(2, "big") + (8 * w).to_bytes(2, "big") + b"\x01\x01\x11\x00"
        files.append(HEAD + _segment(0xFE, b"payload %d" % len(payload)) + TABLES + _segment(0xC0, frame) + SCAN + spread[at : ends[last]].tobytes() + b"\xff\xd9")
        block, at = last + 1, int(ends[last]) + 2
    return files


# -- reading -------------------------------------------------------------------
@dataclass
class Frame:
    """What the markers of a file say."""

    width: int = 0
    height: int = 0
    components: list[dict] = field(default_factory=list)
    quant: dict[int, np.ndarray] = field(default_factory=dict)
    tables: dict[tuple[int, int], Huffman] = field(default_factory=dict)
    restart: int = 0
    comment: bytes = b""
    scan: tuple[int, int] = (0, 0)

    @property
    def mcus(self) -> tuple[int, int]:
        h, v = (max((c[k] for c in self.components), default=1) for k in "hv")
        if len(self.components) == 1:
            h = v = 1
        return -(-self.width // (8 * h)), -(-self.height // (8 * v))

    @property
    def order(self) -> list[int]:
        """The component of each block of an MCU."""
        if len(self.components) == 1:
            return [0]
        return [i for i, c in enumerate(self.components) for _ in range(c["h"] * c["v"])]


_known_tables: dict[bytes, Huffman] = {}


def parse(data: bytes) -> Frame:
    """Read the markers of a baseline file; progressive and arithmetic frames are refused."""
    if data[:2] != HEAD:
        raise ValueError("no start-of-image marker")
    frame, at = Frame(), 2
    while at + 4 <= len(data):
        if data[at] != 0xFF:
            raise ValueError(f"marker expected at {at}")
        marker = data[at + 1]
        if marker == 0xFF:
            at += 1
            continue
        size = int.from_bytes(data[at + 2 : at + 4], "big")
        body = data[at + 4 : at + 2 + size]
        at += 2 + size
        if marker == 0xDB:
            while body:
                wide = body[0] >> 4
                count = 128 if wide else 64
                frame.quant[body[0] & 15] = np.frombuffer(body[1 : 1 + count], ">u2" if wide else np.uint8).astype(np.int64)
                body = body[1 + count :]
        elif marker == 0xC4:
            while body:
                count = sum(body[1:17])
                key = body[1 : 17 + count]
                if key not in _known_tables:
                    if len(_known_tables) > 64:
                        _known_tables.clear()
                    _known_tables[key] = Huffman(list(key[:16]), list(key[16:]))
                frame.tables[body[0] >> 4, body[0] & 15] = _known_tables[key]
                body = body[17 + count :]
        elif marker == 0xC0 or marker == 0xC1:
            if body[0] != 8:
                raise ValueError("only 8-bit samples are read")
            frame.height, frame.width = int.from_bytes(body[1:3], "big"), int.from_bytes(body[3:5], "big")
            frame.components = [{"id": body[6 + 3 * i], "h": body[7 + 3 * i] >> 4, "v": body[7 + 3 * i] & 15, "q": body[8 + 3 * i]} for i in range(body[5])]
        elif 0xC2 <= marker <= 0xCF:
            raise ValueError("not a baseline frame")
        elif marker == 0xDD:
            frame.restart = int.from_bytes(body[:2], "big")
        elif marker == 0xFE:
            frame.comment = bytes(body)
        elif marker == 0xDA:
            if body[0] != len(frame.components):
                raise ValueError("only interleaved scans are read")
            for i in range(body[0]):
                found = next(c for c in frame.components if c["id"] == body[1 + 2 * i])
                found["dc"], found["ac"] = body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15
            end = data.rfind(b"\xff\xd9")
            frame.scan = (at, end if end >= at else len(data))
            return frame
    raise ValueError("no scan")


def _lanes(files: list[bytes], frames: list[Frame]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All scans' bytes without stuffing and restart markers; each interval's start and file."""
    raw = np.frombuffer(b"".join(f[a:b] for f, (a, b) in zip(files, (x.scan for x in frames), strict=True)), np.uint8)
    edge = np.cumsum([0] + [b - a for a, b in (x.scan for x in frames)])
    keep = np.ones(len(raw), bool)
    after = np.flatnonzero(raw[:-1] == 255) + 1
    stuffing = after[raw[after] == 0]
    marks = after[(raw[after] >= 0xD0) & (raw[after] <= 0xD7)]
    keep[stuffing] = False
    keep[marks] = keep[marks - 1] = False
    place = np.concatenate(([0], np.cumsum(keep)))
    starts = np.sort(np.concatenate((edge[:-1], marks + 1)))
    owner = np.searchsorted(edge, starts, side="right") - 1
    return raw[keep], place[starts], owner


def decode(files: list[bytes], frames: list[Frame]) -> list[list[np.ndarray]]:
    """Quantised coefficients (zigzag order) of each component of each file, blocks in scan order.

    Lanes are advanced together; files of different tables or MCU shapes are decoded in groups.
    """
    groups: dict[tuple, list[int]] = {}
    for i, f in enumerate(frames):
        key = tuple((c["h"], c["v"], id(f.tables[0, c["dc"]]), id(f.tables[1, c["ac"]])) for c in f.components)
        groups.setdefault(key, []).append(i)
    out: list = [None] * len(files)
    for members in groups.values():
        for i, got in zip(members, _decode_alike([files[i] for i in members], [frames[i] for i in members]), strict=True):
            out[i] = got
    return out


def _decode_alike(files: list[bytes], frames: list[Frame]) -> list[list[np.ndarray]]:
    order = np.array(frames[0].order)
    parts, per_mcu = frames[0].components, len(order)
    look = np.stack([np.stack((frames[0].tables[0, c["dc"]].look, frames[0].tables[1, c["ac"]].look)) for c in parts])
    data, start, owner = _lanes(files, frames)
    mcus = np.array([f.mcus[0] * f.mcus[1] for f in frames])
    first = np.concatenate(([True], owner[1:] != owner[:-1]))
    nth = np.arange(len(owner)) - np.repeat(np.flatnonzero(first), np.diff(np.append(np.flatnonzero(first), len(owner))))
    step = np.array([f.restart or m for f, m in zip(frames, mcus, strict=True)])[owner]
    todo = np.clip(mcus[owner] - nth * step, 0, step) * per_mcu
    base = np.concatenate(([0], np.cumsum(mcus * per_mcu)))
    block = base[owner] + nth * step * per_mcu
    blocks = np.zeros(int(base[-1]) * 64, np.int16)
    padded = np.concatenate((data, np.full(8, 255, np.uint8))).astype(np.int64)
    bit = start * 8
    limit = len(data) * 8
    done = np.zeros(len(owner), np.int64)  # blocks of each lane
    k = np.zeros(len(owner), np.int64)
    level = np.zeros((len(owner), len(parts)), np.int64)
    live = np.flatnonzero(todo > 0)
    while len(live):
        b, kk = bit[live], k[live]
        byte = b >> 3
        word = (padded[byte] << 32) | (padded[byte + 1] << 24) | (padded[byte + 2] << 16) | (padded[byte + 3] << 8) | padded[byte + 4]
        word <<= b & 7
        which = order[done[live] % per_mcu] if per_mcu > 1 else 0
        found = look[which, (kk > 0).astype(np.int64), (word >> 24) & 0xFFFF]
        size, symbol = found & 31, found >> 5
        if (size == 0).any():
            raise ValueError("no such code in the scan")
        count = symbol & 15
        run = np.where(kk > 0, symbol >> 4, 0)
        raw = (word >> (40 - size - count)) & ((1 << count) - 1)
        value = np.where((count > 0) & (raw < (1 << count >> 1)), raw - (1 << count) + 1, raw)
        b = b + size + count
        bit[live] = b
        start_of = kk == 0
        if start_of.any():
            s = live[start_of]
            comp = which[start_of] if per_mcu > 1 else 0
            level[s, comp] += value[start_of]
            value[start_of] = level[s, comp]
        at = kk + run
        write = (at < 64) & ((count > 0) | start_of)
        blocks[(block[live[write]] + done[live[write]]) * 64 + at[write]] = value[write]
        k[live] = at + 1
        ended = live[(k[live] > 63) | (~start_of & (symbol == 0))]
        if len(ended):
            k[ended] = 0
            done[ended] += 1
            live = live[done[live] < todo[live]]
        if (bit[live] > limit).any():
            raise ValueError("the scan ends early")
    blocks = blocks.reshape(-1, 64)
    result = []
    for i in range(len(files)):
        mine = blocks[base[i] : base[i + 1]].reshape(-1, per_mcu, 64)
        result.append([mine[:, order == c].reshape(-1, 64) for c in range(len(parts))])
    return result


def luminance(frame: Frame, coefficients: list[np.ndarray]) -> np.ndarray:
    """The DC-only thumbnail: one 8-bit sample for each luminance block, clipped at the picture's edge."""
    comp = frame.components[0]
    h, v = (comp["h"], comp["v"]) if len(frame.components) > 1 else (1, 1)
    wide, high = frame.mcus
    dc = coefficients[0][:, 0].astype(np.int64) * int(frame.quant[comp["q"]][0])
    grid = dc.reshape(high, wide, v, h).transpose(0, 2, 1, 3).reshape(high * v, wide * h)
    most_h, most_v = (max(c[x] for c in frame.components) if len(frame.components) > 1 else 1 for x in "hv")
    rows, columns = -(-(-(-frame.height * v // most_v)) // 8), -(-(-(-frame.width * h // most_h)) // 8)
    return np.clip(np.floor_divide(grid[:rows, :columns] + 4, 8) + LEVEL, 0, 255).astype(np.uint8)


def thumbnail_hash(thumb: np.ndarray) -> str:
    """64 bits as hex: whether each cell of an 8 x 8 reduction exceeds its right neighbour (9 columns, nearest)."""
    rows = (np.arange(8) * thumb.shape[0]) // 8
    columns = (np.arange(9) * thumb.shape[1]) // 9
    small = thumb[np.ix_(rows, columns)].astype(np.int64)
    return np.packbits(small[:, :-1] > small[:, 1:]).tobytes().hex()


def feature(frame: Frame, coefficients: list[np.ndarray]) -> str:
    return f"{frame.width}x{frame.height}:{thumbnail_hash(luminance(frame, coefficients))}"


def unpack(frame: Frame, coefficients: list[np.ndarray]) -> bytes:
    """The payload of a file that ``pack`` wrote."""
    size = int(frame.comment.removeprefix(b"payload "))
    return (coefficients[0].reshape(-1)[:size] + LEVEL).astype(np.uint8).tobytes()


def payload_of(text: bytes) -> bytes:
    return text + bytes(-len(text) % BLOCK if text else BLOCK)


# -- DataFrames ----------------------------------------------------------------
def thumbnails(images: DataFrame, column: str = "content") -> DataFrame:
    """``column`` (binary JPEG files) to ``width, height, thumb_width, thumb_height, thumb_hash, thumb``; null where unreadable or null."""
    schema = "width int, height int, thumb_width int, thumb_height int, thumb_hash string, thumb binary, error string"

    def run(batches):
        for batch in batches:
            rows = []
            for value in batch.column(0):
                try:
                    raw = value.as_py()
                    if raw is None:
                        raise ValueError("null")
                    frame = parse(raw)
                    thumb = luminance(frame, decode([raw], [frame])[0])
                    rows.append((frame.width, frame.height, thumb.shape[1], thumb.shape[0], thumbnail_hash(thumb), thumb.tobytes(), None))
                except (ValueError, KeyError, IndexError, StopIteration) as e:
                    rows.append((None,) * 6 + (str(e),))
            kinds = [pa.int32()] * 4 + [pa.string(), pa.binary(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=[f.split()[0] for f in schema.split(", ")])

    return images.select(column).mapInArrow(run, schema)


def store_documents(docs: DataFrame, keep_media: bool = False) -> DataFrame:
    """Each text stored as a JPEG payload and read back; digests, features and (if asked) the file."""

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        data, offsets = common.utf8(part.column("text"))
        n = part.num_rows
        size = np.diff(offsets)
        payloads = [payload_of(data[offsets[r] : offsets[r + 1]].tobytes()) for r in range(n)]
        files = pack(payloads)
        frames = [parse(f) for f in files]
        back_length, back_sha, tail, media_sha, features = [], [], [], [], []
        for file, frame, coefficients in zip(files, frames, decode(files, frames), strict=True):
            payload = unpack(frame, coefficients)
            back_length.append(len(payload))
            back_sha.append(hashlib.sha256(payload).hexdigest())
            tail.append(zlib.crc32(payload[-64:]))
            media_sha.append(hashlib.sha256(file).hexdigest())
            features.append(feature(frame, coefficients))
        ints = [pa.array(v, pa.int64()) for v in (size, back_length, tail, [len(f) for f in files])]
        columns = [part.column("doc_id"), ints[0], ints[1], pa.array(back_sha, pa.string()), ints[2], ints[3], pa.array(media_sha, pa.string()), pa.array(features, pa.string()), pa.array(files if keep_media else [None] * n, pa.binary())]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media"])

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, media binary"
    return common.map_slices(docs.select("doc_id", "text"), kernel, schema)


def op3_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document as a stored JPEG payload, read back."""
    return store_documents(common.read_table(spark, sf_dir, "documents")).drop("media")
