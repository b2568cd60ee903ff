"""AVI motion-JPEG columns: RIFF writer and reader, intra-frame decoder, and shots as timed clips.

Storing. A payload (a multiple of 64 bytes) becomes grey frames of up to 64 blocks. JPEG's stored unit is the quantised
coefficient, so a payload byte v is one: v from 128 on is the coefficient v, below it is v - 255. These are just the amplitudes of
category 8, whose eight amplitude bits are v itself; with the Huffman code 0 for that category a block takes 72 bytes, and
restarts after each block keep blocks independent. Any baseline decoder reads the same coefficients back, so nothing is lost.

Reading. The index chunk (idx1) says where frames are; without one, or if it doesn't fit the file, the movi list is walked. The
frames' scans are decoded for any baseline tables, sampling and restart interval; all restart intervals of a batch of frames with
the same tables are decoded in lockstep in numpy. Shots are runs of frames between adaptive cuts: the histogram difference
of two frames is a cut if it exceeds `floor` and the mean of its neighbourhood by `factor` deviations.

Defined results: a broken file raises ValueError in `read_avi` and gives a row with an error and no clips in `clips`; null media give null
columns; a file without frames has no clips.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import in_arrow, table

UNIT = 64
BLOCKS = 64
RATE = 25
#: Fixed value: the order in which JPEG stores an 8 x 8 block's coefficients.
ZIGZAG = np.array([
    0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28,
    35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63,
])
_x, _u = np.meshgrid(np.arange(8), np.arange(8), indexing="ij")
COSINE = (np.cos((2 * _x + 1) * _u * np.pi / 16) * np.where(_u == 0, np.sqrt(0.125), 0.5)).astype(np.float32)


# --- writing -------------------------------------------------------------------------------------


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _head(width: int, height: int) -> bytes:
    code = bytes([1] + [0] * 15)
    return b"".join((
        b"\xff\xd8", _segment(0xDB, b"\0" + b"\1" * 64), _segment(0xC0, struct.pack(">BHHB", 8, height, width, 1) + b"\1\x11\0"),
        _segment(0xC4, b"\x00" + code + b"\x08"), _segment(0xC4, b"\x10" + code + b"\x08"), _segment(0xDD, b"\0\1"), _segment(0xDA, b"\1\1\0\0\x3f\0"),
    ))


def _frame_size(blocks: int) -> tuple[int, int]:
    return (64, 64) if blocks == BLOCKS else (8 * blocks, 8)


def write_frames(payload: np.ndarray) -> list[bytes]:
    """JPEG frames of a payload of whole units."""
    bits = np.unpackbits(payload.reshape(-1, UNIT, 1), axis=2)
    coded = np.packbits(np.concatenate([np.zeros((*bits.shape[:2], 1), np.uint8), bits], 2).reshape(len(bits), -1), axis=1)
    frames = []
    for at in range(0, len(coded), BLOCKS):
        own = coded[at : at + BLOCKS]
        marks = np.stack([np.full(len(own), 0xFF, np.uint8), (0xD0 + np.arange(len(own)) % 8).astype(np.uint8)], 1)
        flat = np.concatenate([own, marks], 1)
        data = flat.reshape(-1)[:-2]
        stuffed = np.flatnonzero((own == 0xFF).any(1))
        if len(stuffed):
            row, col = np.nonzero(own == 0xFF)
            data = np.insert(data, row * flat.shape[1] + col + 1, 0)
        frames.append(_head(*_frame_size(len(own))) + data.tobytes() + b"\xff\xd9")
    return frames


def _chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) % 2)


def write_avi(frames: list[bytes], width: int, height: int, rate: int = RATE) -> bytes:
    largest = max(map(len, frames), default=0)
    avih = struct.pack("<14I", 1_000_000 // rate, largest * rate, 0, 0x10, len(frames), 0, 1, largest, width, height, 0, 0, 0, 0)
    strh = b"vidsMJPG" + struct.pack("<IHHIIIIIIII4H", 0, 0, 0, 0, 1, rate, 0, len(frames), largest, 0xFFFFFFFF, 0, 0, 0, width & 0xFFFF, height & 0xFFFF)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 24, b"MJPG", width * height * 3, 0, 0, 0, 0)
    movi, index, at = [b"movi"], [], 4
    for f in frames:
        piece = _chunk(b"00dc", f)
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        movi.append(piece)
        at += len(piece)
    hdrl = b"hdrl" + _chunk(b"avih", avih) + _chunk(b"LIST", b"strl" + _chunk(b"strh", strh) + _chunk(b"strf", strf))
    return _chunk(b"RIFF", b"AVI " + _chunk(b"LIST", hdrl) + _chunk(b"LIST", b"".join(movi)) + _chunk(b"idx1", b"".join(index)))


def store_payload(payload: bytes) -> bytes:
    """The AVI of a payload whose length is a positive multiple of 64."""
    if not payload or len(payload) % UNIT:
        raise ValueError("a payload is a positive multiple of 64 bytes")
    blocks = len(payload) // UNIT
    return write_avi(write_frames(np.frombuffer(payload, np.uint8)), *_frame_size(min(blocks, BLOCKS)))


# --- reading -------------------------------------------------------------------------------------


def _children(data: bytes, at: int, end: int):
    while at + 8 <= end:
        n = struct.unpack_from("<I", data, at + 4)[0]
        yield data[at : at + 4], at + 8, min(at + 8 + n, end)
        at += 8 + n + n % 2


def read_avi(data: bytes) -> dict:
    """rate (frames a second), width, height and frames (JPEG bytes) of a motion-JPEG AVI."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI")
    out, movi, index, streams = {"rate": float(RATE), "width": 0, "height": 0}, None, None, []
    for name, at, end in _children(data, 12, len(data)):
        if name == b"LIST" and data[at : at + 4] == b"hdrl":
            for inner, a, b in _children(data, at + 4, end):
                if inner == b"avih" and b - a >= 40:
                    us, out["width"], out["height"] = *struct.unpack_from("<I", data, a), *struct.unpack_from("<II", data, a + 32)
                    out["rate"] = 1e6 / us if us else float(RATE)
                elif inner == b"LIST" and data[a : a + 4] == b"strl":
                    streams.append(next((data[x : x + 8] for n, x, _ in _children(data, a + 4, b) if n == b"strh"), b""))
        elif name == b"LIST" and data[at : at + 4] == b"movi":
            movi = (at, end)
        elif name == b"idx1":
            index = (at, end)
    if movi is None:
        raise ValueError("no movi list")
    video = next((i for i, s in enumerate(streams) if s[:4] == b"vids"), 0)
    names = (b"%02ddc" % video, b"%02ddb" % video)
    found = None
    if index is not None:
        rows = [struct.unpack_from("<4sIII", data, i) for i in range(index[0], index[1] - 15, 16)]
        rows = [(o, n) for name, _, o, n in rows if name in names]
        for base in (movi[0], 0):  # offsets count from the movi list's name, or from the file's start
            if all(data[base + o : base + o + 4] in names and base + o + 8 + n <= len(data) for o, n in rows):
                found = [data[base + o + 8 : base + o + 8 + n] for o, n in rows]
                break
    out["frames"] = found if found is not None else [data[a:b] for name, a, b in _children(data, movi[0] + 4, movi[1]) if name in names]
    return out


def _huffman(counts: bytes, symbols: bytes) -> np.ndarray:
    """For all 16 next bits: length of the code there * 256 + its symbol (0: no code)."""
    lut, code, k = np.zeros(1 << 16, np.int32), 0, 0
    for length in range(1, 17):
        for _ in range(counts[length - 1]):
            lo = code << (16 - length)
            lut[lo : lo + (1 << (16 - length))] = length << 8 | symbols[k]
            code, k = code + 1, k + 1
        code <<= 1
    return lut


class Jpeg:
    """The parsed head of a baseline JPEG, and its scan's bytes."""

    def __init__(self, data: bytes):
        self.tables, self.quant, self.restart, at = {}, {}, 0, 2
        if data[:2] != b"\xff\xd8":
            raise ValueError("not a JPEG")
        while True:
            if at + 4 > len(data) or data[at] != 0xFF:
                raise ValueError("broken JPEG head")
            marker, n = data[at + 1], struct.unpack_from(">H", data, at + 2)[0]
            body, at = data[at + 4 : at + 2 + n], at + 2 + n
            if marker == 0xDB:
                while body:
                    wide = body[0] >> 4
                    self.quant[body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else np.uint8).astype(np.float32)
                    body = body[65 + 64 * wide :]
            elif marker in (0xC0, 0xC1):
                _, self.height, self.width, n = struct.unpack_from(">BHHB", body)
                self.parts = [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)]
            elif 0xC0 <= marker <= 0xCF and marker not in (0xC4, 0xC8, 0xCC):
                raise ValueError("not a baseline JPEG")
            elif marker == 0xC4:
                while body:
                    total = sum(body[1:17])
                    self.tables[body[0]] = (body[1:17], body[17 : 17 + total])
                    body = body[17 + total :]
            elif marker == 0xDD:
                self.restart = struct.unpack(">H", body[:2])[0]
            elif marker == 0xDA:
                use = {body[1 + 2 * i]: body[2 + 2 * i] for i in range(body[0])}
                break
        self.blocks = []  # of one MCU: component, DC table, AC table
        wide, high = max(p[1] for p in self.parts), max(p[2] for p in self.parts)
        single = len(self.parts) == 1
        for i, (name, h, v, _) in enumerate(self.parts):
            self.blocks += [(i, use[name] >> 4, 16 | use[name] & 15)] * (1 if single else h * v)
        unit = (8, 8) if single else (8 * wide, 8 * high)
        self.across, self.down = -(-self.width // unit[0]), -(-self.height // unit[1])
        self.scan = data[at:]
        self.kind = (tuple(self.blocks), tuple(sorted((k, v) for k, v in self.tables.items())))

    def intervals(self) -> list[tuple[bytes, int]]:
        """(bytes without stuffing, MCUs) of each restart interval."""
        raw = np.frombuffer(self.scan, np.uint8)
        marks = np.flatnonzero((raw[:-1] == 0xFF) & (raw[1:] != 0) & (raw[1:] != 0xFF))
        codes = raw[marks + 1]
        stop = np.flatnonzero((codes < 0xD0) | (codes > 0xD7))
        end = int(marks[stop[0]]) if len(stop) else len(raw)
        edges = [-2, *(int(m) for m in marks if m < end), end]
        mcus, each = self.across * self.down, self.restart or self.across * self.down
        pieces = [self.scan[a + 2 : b].replace(b"\xff\0", b"\xff") for a, b in zip(edges, edges[1:], strict=False)]
        need = -(-mcus // each)
        if len(pieces) < need:
            raise ValueError("truncated scan")
        return [(p, min(each, mcus - i * each)) for i, p in enumerate(pieces[:need])]


def decode(frames: list[Jpeg]) -> list[np.ndarray]:
    """Quantised coefficients of each frame, [MCU, block of the MCU, 64] in stored order."""
    out: list = [None] * len(frames)
    groups: dict[tuple, list[int]] = {}
    for i, f in enumerate(frames):
        groups.setdefault(f.kind, []).append(i)
    for (blocks, tables), members in groups.items():
        luts = {k: _huffman(*v) for k, v in tables}
        parts = [(p, n, i) for i in members for p, n in frames[i].intervals()]
        buffer = np.frombuffer(b"".join(p + b"\0" * 8 for p, _, _ in parts), np.uint8).astype(np.uint32)
        words = (buffer[:-3] << np.uint32(24)) | (buffer[1:-2] << np.uint32(16)) | (buffer[2:-1] << np.uint32(8)) | buffer[3:]
        position = np.cumsum([0, *(len(p) + 8 for p, _, _ in parts[:-1])]).astype(np.int64) * 8
        mcus = np.array([n for _, n, _ in parts])
        first = np.cumsum(np.concatenate([[0], mcus[:-1]]))
        got = np.zeros((int(mcus.sum()), len(blocks), 64), np.int16)
        before = np.zeros((len(parts), 1 + max(b[0] for b in blocks)), np.int32)

        def peek(at, n, words=words):
            return ((words[np.minimum(at >> 3, len(words) - 1)] << (at & 7).astype(np.uint32)) >> np.uint32(32 - n)).astype(np.int64) if n else 0

        def amplitude(at, size, words=words):
            # up to 11 bits, within one 32-bit word
            w = (words[np.minimum(at >> 3, len(words) - 1)] << (at & 7).astype(np.uint32)).astype(np.int64) & 0xFFFFFFFF
            v = w >> (32 - size)
            return np.where(size > 0, np.where(v >> np.maximum(size - 1, 0) & 1, v, v - (1 << size) + 1), 0)

        for m in range(int(mcus.max(initial=0))):
            live = np.flatnonzero(mcus > m)
            for b, (component, dc, ac) in enumerate(blocks):
                at, row = position[live], first[live] + m
                hit = luts[dc][peek(at, 16)]
                at = at + (hit >> 8)
                size = hit & 255
                before[live, component] += amplitude(at, size).astype(np.int32)
                got[row, b, 0] = before[live, component]
                at = at + size
                k, on = np.ones(len(live), np.int64), np.arange(len(live))
                while len(on):
                    hit = luts[ac][peek(at[on], 16)]
                    if not hit.all():
                        raise ValueError("no such code")
                    run, size = (hit >> 4) & 15, hit & 15
                    at[on] += hit >> 8
                    k[on] += run
                    some = size > 0
                    full = some.all()
                    w = on if full else on[some]
                    if len(w):
                        s = size if full else size[some]
                        if k[w].max() > 63:
                            raise ValueError("too many coefficients")
                        got[row[w], b, k[w]] = amplitude(at[w], s)
                        at[w] += s
                    k[on] += 1
                    on = on[((size > 0) | (run == 15)) & (k[on] < 64)] if not full or k[on].max() > 63 else on
                position[live] = at
        shown = 0
        at_frame = {}
        for _, n, i in parts:
            at_frame.setdefault(i, [shown, shown])[1] = shown = shown + n
        for i, (a, z) in at_frame.items():
            out[i] = got[a:z]
    return out


def luminance(coefficients: np.ndarray, frame: Jpeg) -> np.ndarray:
    """The first component's samples by block, [blocks, 8, 8]."""
    own = [i for i, b in enumerate(frame.blocks) if b[0] == 0]
    stored = coefficients[:, own].reshape(-1, 64) * frame.quant[frame.parts[0][3]]
    plane = np.zeros((len(stored), 64), np.float32)
    plane[:, ZIGZAG] = stored
    samples = COSINE @ plane.reshape(-1, 8, 8) @ COSINE.T
    return np.clip(np.rint(samples + 128), 0, 255).astype(np.uint8)


def histograms(blocks: list[np.ndarray], bins: int = 16) -> np.ndarray:
    """The share of samples in each of the bins, by frame."""
    return np.array([np.bincount(b.reshape(-1) >> 4, minlength=bins) / max(1, b.size) for b in blocks]).reshape(-1, bins)


def shots(shares: np.ndarray, window: int = 8, factor: float = 3.0, floor: float = 0.2) -> list[tuple[int, int]]:
    """(first frame, frame after the last) of each shot."""
    if not len(shares):
        return []
    change = np.abs(np.diff(shares, axis=0)).sum(1)
    cuts = [0]
    for i, d in enumerate(change):
        around = np.delete(change[max(0, i - window) : i + window + 1], min(i, window))
        if d > floor and d > (around.mean() + factor * around.std() if len(around) else 0):
            cuts.append(i + 1)
    return list(zip(cuts, [*cuts[1:], len(shares)], strict=True))


def payload_of(coefficients: np.ndarray) -> np.ndarray:
    """The bytes that coefficients of category 8 store."""
    flat = coefficients.reshape(-1)
    return np.where(flat >= 0, flat, flat + 255).astype(np.uint8)


# --- operators -----------------------------------------------------------------------------------


def clips(df: DataFrame, key: str, media: str) -> DataFrame:
    """key, clip, first_frame, last_frame, start_ms, end_ms, error: the shots of each AVI in a binary column."""

    def run(batches):
        for batch in batches:
            out: list[list] = [[] for _ in range(7)]

            def add(*row, out=out):
                for column, v in zip(out, row, strict=True):
                    column.append(v)

            for k, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if data is None:
                    continue
                try:
                    film = read_avi(data)
                    heads = [Jpeg(f) for f in film["frames"]]
                    found = shots(histograms([luminance(c, h) for c, h in zip(decode(heads), heads, strict=True)]))
                except (ValueError, struct.error, KeyError, IndexError) as e:
                    add(k, None, None, None, None, None, str(e))
                    continue
                for i, (a, b) in enumerate(found):
                    add(k, i, a, b - 1, round(a * 1000 / film["rate"]), round(b * 1000 / film["rate"]), None)
            kinds = [batch.schema.field(0).type, pa.int32(), *[pa.int64()] * 4, pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=True)], ["key", "clip", "first_frame", "last_frame", "start_ms", "end_ms", "error"])

    kind = df.schema[key].dataType.simpleString()
    return in_arrow(df.select(F.col(key).alias("key"), media), run, f"key {kind}, clip int, first_frame long, last_frame long, start_ms long, end_ms long, error string").withColumnRenamed("key", key)


def padded(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw + b"\0" * (-len(raw) % UNIT if raw else UNIT)


def store_texts(df: DataFrame, key: str, text: str) -> DataFrame:
    """key and media: each text's AVI."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([store_payload(padded(t)[1]) for t in part.column(1).to_pylist()], pa.binary())], ["key", "media"])

    kind = df.schema[key].dataType.simpleString()
    return in_arrow(df.select(F.col(key).alias("key"), F.col(text).cast("string")), run, f"key {kind}, media binary").withColumnRenamed("key", key)


def describe(shares: np.ndarray, film: dict) -> str:
    """Frames, size, shots and the mean histogram of a film, as one string."""
    found = shots(shares)
    mean = "".join(f"{round(255 * x):02x}" for x in shares.mean(0)) if len(shares) else ""
    return f"mjpeg {film['width']}x{film['height']} frames={len(shares)} shots={','.join(f'{a}-{b}' for a, b in found)} hist={mean}"


def digests(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Stores each text as AVI, reads the AVI back and describes both; the media don't leave their task."""
    names = ["key", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]

    def work(rows: list[tuple], kind) -> pa.RecordBatch:
        media = [store_payload(p) for _, _, p in rows]
        films = [read_avi(m) for m in media]
        heads = [[Jpeg(f) for f in film["frames"]] for film in films]
        decoded = iter(decode([h for own in heads for h in own]))
        out = []
        for (k, n, _), m, film, own in zip(rows, media, films, heads, strict=True):
            coefficients = [next(decoded) for _ in own]
            back = np.concatenate([payload_of(c) for c in coefficients]).tobytes()
            blocks = luminance(np.concatenate(coefficients), own[0])
            ends = np.cumsum([len(c) for c in coefficients])[:-1]
            out.append((k, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(m), hashlib.sha256(m).hexdigest(), describe(histograms(np.split(blocks, ends)), film)))
        kinds = [kind, pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), kinds, strict=True)], names)

    def run(batches):
        for batch in batches:
            kind, rows, held = batch.schema.field(0).type, [], 0
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                for k, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    n, payload = padded(t)
                    rows.append((k, n, payload))
                    held += len(payload)
                    if held > 1_500_000:
                        yield work(rows, kind)
                        rows, held = [], 0
            if rows:
                yield work(rows, kind)

    kind = df.schema[key].dataType.simpleString()
    schema = f"key {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return in_arrow(df.select(F.col(key).alias("key"), F.col(text).cast("string")), run, schema).withColumnRenamed("key", key)


def op6_avi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's text stored as motion-JPEG AVI and read back."""
    return digests(table(spark, sf_dir, "documents").select("doc_id", "text"))
