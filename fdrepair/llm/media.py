"""AVI motion-JPEG: RIFF writing and parsing, intra frames, shots and timed clips.

Bytes are stored as 8-bit grey samples, ``WIDTH`` to a row, in frames of at most ``HEIGHT`` rows. Each frame is
a lossless JPEG (SOF3, left predictor) whose restart interval is one row, so that every row is a lane of its
own: lanes of many frames and files are packed, and unpacked, in step by array operations. Baseline
JPEG frames (SOF0, Huffman tables in the frame) are read as well.

A file's index (idx1) gives the frames; a file without one is walked chunk by chunk. Shots: the distance
of consecutive frames' histograms is compared with the mean and deviation of the distances before it
in the same shot, so that the threshold follows the material.

Defined results: a null or empty text becomes one group of spaces; long texts become more frames; equal bytes give
equal files; a file or frame that can't be read gives no clips (``clips``); repeated rows
are repeated; extra columns are kept by ``store`` and ``clips``.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

UNIT = 192  # payloads are filled up to a multiple of it
WIDTH, HEIGHT, RATE = 64, 24, 25
GROUP_BYTES = 1 << 19  # payload bytes packed or unpacked at once
BINS = 16
# Code lengths 1-16 and categories of the usual luminance DC table.
DC_COUNTS = (0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0)
DC_VALUES = tuple(range(12))


def canonical_codes(counts, values) -> dict[int, tuple[int, int]]:
    """Symbol to (code, length) of a JPEG Huffman table."""
    out, code, k = {}, 0, 0
    for length, n in enumerate(counts, 1):
        for _ in range(n):
            out[values[k]] = (code, length)
            code, k = code + 1, k + 1
        code <<= 1
    return out


def lookup(counts, values, bits: int = 16) -> tuple[np.ndarray, np.ndarray]:
    """(symbol, length) by the next ``bits`` bits."""
    symbol, length = np.zeros(1 << bits, np.int64), np.zeros(1 << bits, np.int64)
    for s, (code, n) in canonical_codes(counts, values).items():
        symbol[code << (bits - n) : (code + 1) << (bits - n)] = s
        length[code << (bits - n) : (code + 1) << (bits - n)] = n
    return symbol, length


_codes = canonical_codes(DC_COUNTS, DC_VALUES)
_code = np.array([_codes[c][0] for c in range(9)])
_length = np.array([_codes[c][1] for c in range(9)])
_category = np.array([int(x).bit_length() for x in range(256)])


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


_TABLES = _segment(0xC4, bytes([0, *DC_COUNTS, *DC_VALUES])) + _segment(0xDD, struct.pack(">H", WIDTH))
_SCAN = _segment(0xDA, bytes([1, 1, 0, 1, 0, 0]))


def jpeg_frames(rows: np.ndarray, heights: list[int]) -> list[bytes]:
    """Lossless JPEG frames of consecutive rows of samples (all of one width)."""
    n, width = rows.shape
    diff = np.diff(rows.astype(np.int64), axis=1, prepend=128)
    size = _category[np.abs(diff)]
    extra = np.where(diff < 0, diff + (1 << size) - 1, diff)
    value, bits = (_code[size] << size) | extra, _length[size] + size
    ends = np.cumsum(bits, axis=1)
    room = (int(ends[:, -1].max()) + 7) // 8 * 8
    start = (np.arange(n)[:, None] * room + ends - bits).ravel()
    flat_bits, flat_value = bits.ravel(), value.ravel()
    first = np.cumsum(flat_bits) - flat_bits
    inner = np.arange(int(flat_bits.sum())) - np.repeat(first, flat_bits)
    grid = np.ones(n * room, np.uint8)  # the filling bits are ones
    grid[np.repeat(start, flat_bits) + inner] = (np.repeat(flat_value, flat_bits) >> (np.repeat(flat_bits, flat_bits) - 1 - inner)) & 1
    packed = np.packbits(grid.reshape(n, room), axis=1)
    used = (ends[:, -1] + 7) // 8
    mask = np.arange(room // 8)[None, :] < used[:, None]
    owner = np.repeat(np.arange(n), used)
    data = packed[mask]
    stuffed = np.repeat(data, 1 + (data == 255))
    at = np.cumsum(1 + (data == 255)) - 1
    stuffed[at[data == 255]] = 0
    per_row = used + np.bincount(owner[data == 255], minlength=n)
    stops = np.cumsum(per_row).tolist()
    raw, out, row = stuffed.tobytes(), [], 0
    begin = 0
    for h in heights:
        lanes = []
        for k in range(h):
            stop = stops[row + k]
            lanes.append(raw[begin:stop])
            if k + 1 < h:
                lanes.append(bytes((0xFF, 0xD0 + k % 8)))
            begin = stop
        row += h
        head = b"\xff\xd8" + _segment(0xC3, struct.pack(">BHHB", 8, h, width, 1) + bytes([1, 0x11, 0])) + _TABLES + _SCAN
        out.append(head + b"".join(lanes) + b"\xff\xd9")
    return out


def parse_jpeg(frame: bytes) -> dict:
    """Header fields, tables and the place of the scan of a one-scan JPEG."""
    if frame[:2] != b"\xff\xd8":
        raise ValueError("no JPEG")
    at, out = 2, {"dc": {}, "ac": {}, "quant": {}, "interval": 0}
    while True:
        if at + 4 > len(frame) or frame[at] != 0xFF:
            raise ValueError("broken JPEG")
        marker, size = frame[at + 1], struct.unpack_from(">H", frame, at + 2)[0]
        body = frame[at + 4 : at + 2 + size]
        at += 2 + size
        if marker in (0xC0, 0xC3):
            depth, height, width, n = struct.unpack_from(">BHHB", body)
            parts = [(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k]) for k in range(n)]
            out |= {"kind": marker, "depth": depth, "height": height, "width": width, "parts": parts}
        elif marker == 0xC4:
            k = 0
            while k < len(body):
                counts = tuple(body[k + 1 : k + 17])
                out["ac" if body[k] >> 4 else "dc"][body[k] & 15] = (counts, tuple(body[k + 17 : k + 17 + sum(counts)]))
                k += 17 + sum(counts)
        elif marker == 0xDB:
            k = 0
            while k < len(body):
                wide = body[k] >> 4
                out["quant"][body[k] & 15] = np.frombuffer(body, ">u2" if wide else "u1", 64, k + 1).astype(float)
                k += 1 + 64 * (1 + wide)
        elif marker == 0xDD:
            out["interval"] = struct.unpack(">H", body)[0]
        elif marker == 0xDA:
            n = body[0]
            return out | {"tables": [body[2 + 2 * k] for k in range(n)], "predictor": body[1 + 2 * n], "scan": at}
        elif marker in (0xC1, 0xC2, *range(0xC5, 0xD0)):
            raise ValueError("JPEG kind not supported")


def lanes_of(scan: bytes) -> list[bytes]:
    """The entropy-coded intervals of a scan, without stuffing."""
    out, begin, at = [], 0, scan.find(b"\xff")
    while at >= 0:
        follows = scan[at + 1] if at + 1 < len(scan) else 0xD9
        if follows:
            out.append(scan[begin:at].replace(b"\xff\x00", b"\xff"))
            begin = at + 2
            if not 0xD0 <= follows <= 0xD7:
                return out
        at = scan.find(b"\xff", at + 2)
    return [*out, scan[begin:].replace(b"\xff\x00", b"\xff")]


def lossless_rows(lanes: list[bytes], width: int, table=(DC_COUNTS, DC_VALUES)) -> np.ndarray:
    """Rows of samples, one of each lane, all lanes in step."""
    symbol, length = lookup(*table)
    sizes = np.fromiter(map(len, lanes), np.int64, len(lanes))
    data = np.frombuffer(b"".join(x + b"\xff\xff\xff\xff" for x in lanes), np.uint8).astype(np.uint32)
    first = np.cumsum(sizes + 4) - sizes - 4
    words = (data[:-3] << 24) | (data[1:-2] << 16) | (data[2:-1] << 8) | data[3:]
    limit = len(words) - 1
    at, last = first * 8, np.full(len(lanes), 128, np.int64)
    out = np.empty((width, len(lanes)), np.uint8)
    for x in range(width):
        window = (words[np.minimum(at >> 3, limit)].astype(np.int64) << (at & 7)) & 0xFFFFFFFF
        head = window >> 16
        size, n = symbol[head], length[head]
        extra = (window >> (32 - n - size)) & ((1 << size) - 1)
        last = (last + np.where(extra < (1 << size) >> 1, extra - (1 << size) + 1, extra)) & 0xFFFF
        out[x] = last
        at = at + n + size
    if ((at + 7) // 8 > first + sizes).any():
        raise ValueError("a lane ends early")
    return out.T


def baseline_luma(frame: bytes, head: dict) -> np.ndarray:
    """The first component of a baseline JPEG, decoded interval by interval."""
    zigzag = sorted(range(64), key=lambda k: (k // 8 + k % 8, (k // 8 if (k // 8 + k % 8) % 2 else k % 8)))
    u = np.arange(8)
    basis = np.cos((2 * u[None, :] + 1) * u[:, None] * np.pi / 16) * np.where(u == 0, np.sqrt(1 / 8), 0.5)[:, None]
    parts = head["parts"]
    hmax, vmax = max(p[1] for p in parts), max(p[2] for p in parts)
    mcus_x, mcus_y = -(-head["width"] // (8 * hmax)), -(-head["height"] // (8 * vmax))
    if len(parts) == 1:
        hmax = vmax = 1
        parts = [(parts[0][0], 1, 1, parts[0][3])]
        mcus_x, mcus_y = -(-head["width"] // 8), -(-head["height"] // 8)
    decoders = [(lookup(*head["dc"][t >> 4]), lookup(*head["ac"][t & 15])) for t in head["tables"]]
    h0, v0 = parts[0][1:3]
    image = np.zeros((mcus_y * v0 * 8, mcus_x * h0 * 8))
    total, done = mcus_x * mcus_y, 0
    for lane in lanes_of(frame[head["scan"] :]):
        bits, at = int.from_bytes(lane + b"\xff" * 8, "big"), 0
        room = (len(lane) + 8) * 8

        def peek(n: int) -> int:
            return (bits >> (room - at - n)) & ((1 << n) - 1)

        last = [0] * len(parts)
        for _ in range(min(head["interval"] or total, total - done)):
            for c, (_, h, v, q) in enumerate(parts):
                for b in range(h * v):
                    block = np.zeros(64)
                    (ds, dn), (as_, an) = decoders[c]
                    code = peek(16)
                    at, size = at + int(dn[code]), int(ds[code])
                    value = peek(size) if size else 0
                    at += size
                    last[c] += value if not size or value >> (size - 1) else value - (1 << size) + 1
                    block[0], k = last[c], 1
                    while k < 64:
                        code = peek(16)
                        at, run = at + int(an[code]), int(as_[code])
                        if not an[code] or at > room:
                            raise ValueError("broken scan")
                        if run == 0:
                            break
                        k, size = k + (run >> 4), run & 15
                        if size and k < 64:
                            value = peek(size)
                            at += size
                            block[zigzag[k]] = value if value >> (size - 1) else value - (1 << size) + 1
                        k += 1
                    if c == 0:
                        table = np.zeros(64)
                        table[zigzag] = head["quant"][q]
                        y = (done // mcus_x * v + b // h) * 8
                        x = (done % mcus_x * h + b % h) * 8
                        image[y : y + 8, x : x + 8] = basis.T @ (block * table).reshape(8, 8) @ basis
            done += 1
    return np.clip(np.round(image + 128), 0, 255).astype(np.uint8)[: head["height"], : head["width"]]


def decode_frames(frames: list[bytes]) -> list[np.ndarray]:
    """Samples of each frame; all rows of lossless frames of one width are decoded together."""
    heads = [parse_jpeg(f) for f in frames]
    out: list = [None] * len(frames)
    together: dict[tuple, list[tuple[int, list[bytes]]]] = {}
    for k, (f, h) in enumerate(zip(frames, heads)):
        if h["kind"] == 0xC0:
            out[k] = baseline_luma(f, h)
        elif h["predictor"] == 1 and h["interval"] == h["width"] and len(h["parts"]) == 1 and h["depth"] == 8:
            lanes = lanes_of(f[h["scan"] :])
            if len(lanes) != h["height"]:
                raise ValueError("rows are missing")
            together.setdefault((h["width"], h["dc"][h["tables"][0] >> 4]), []).append((k, lanes))
        else:
            raise ValueError("JPEG kind not supported")
    for (width, table), members in together.items():
        rows, at = lossless_rows([x for _, lanes in members for x in lanes], width, table), 0
        for k, lanes in members:
            out[k] = rows[at : at + len(lanes)]
            at += len(lanes)
    return out


def _chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)


def avi(frames: list[bytes], width: int = WIDTH, height: int = HEIGHT, rate: int = RATE) -> bytes:
    """A RIFF file of JPEG frames with its index."""
    most = max(map(len, frames), default=0)
    avih = struct.pack("<14I", 1_000_000 // rate, most * rate, 0, 0x10, len(frames), 0, 1, most, width, height, 0, 0, 0, 0)
    strh = struct.pack("<4s4sIHHIIIIIIIIHHHH", b"vids", b"MJPG", 0, 0, 0, 0, 1, rate, 0, len(frames), most, 0xFFFFFFFF, 0, 0, 0, width, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 8, b"MJPG", width * height, 0, 0, 0, 0)
    hdrl = _chunk(b"LIST", b"hdrl" + _chunk(b"avih", avih) + _chunk(b"LIST", b"strl" + _chunk(b"strh", strh) + _chunk(b"strf", strf)))
    parts, index, at = [], [], 4
    for f in frames:
        parts.append(_chunk(b"00dc", f))
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        at += len(parts[-1])
    body = b"AVI " + hdrl + _chunk(b"LIST", b"movi" + b"".join(parts)) + _chunk(b"idx1", b"".join(index))
    return b"RIFF" + struct.pack("<I", len(body)) + body


def read_avi(data: bytes) -> tuple[float, list[bytes]]:
    """Seconds of a frame and the frames of the first video stream, by the index or else in order."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("no AVI file")
    second, movi, index, at = 1 / RATE, None, None, 12
    while at + 8 <= len(data):
        name, size = struct.unpack_from("<4sI", data, at)
        kind = data[at + 8 : at + 12] if name == b"LIST" else b""
        if name == b"avih" and size >= 4:
            second = struct.unpack_from("<I", data, at + 8)[0] / 1e6 or second
        elif kind == b"movi":
            movi = (at + 8, min(len(data), at + 8 + size))
        elif name == b"idx1":
            index = data[at + 8 : at + 8 + size]
        at += 12 if kind == b"hdrl" else 8 + size + (size & 1)
    if movi is None:
        raise ValueError("no frames")
    if index:
        entries = [struct.unpack_from("<4sIII", index, k) for k in range(0, len(index) - 15, 16)]
        entries = [(o, n) for name, _, o, n in entries if name[2:] in (b"dc", b"db")]
        base = movi[0] if entries and data[movi[0] + entries[0][0] :movi[0] + entries[0][0] + 4][2:4] in (b"dc", b"db") else 0
        return second, [data[base + o + 8 : base + o + 8 + n] for o, n in entries]
    frames, at = [], movi[0] + 4
    while at + 8 <= movi[1]:
        name, size = struct.unpack_from("<4sI", data, at)
        if name[2:] in (b"dc", b"db"):
            frames.append(data[at + 8 : at + 8 + size])
        at += 8 + size + (size & 1)
    return second, frames


def shots(frames: list[np.ndarray], width: float = 2.5, floor: float = 0.08) -> list[tuple[int, int]]:
    """(first, behind the last) frame of each shot."""
    if not frames:
        return []
    shares = np.array([np.bincount(f.ravel() >> 4, minlength=BINS) / f.size for f in frames])
    steps = np.abs(np.diff(shares, axis=0)).sum(axis=1) / 2
    out, first, n, total, squares = [], 0, 0, 0.0, 0.0
    for k, d in enumerate(steps.tolist(), 1):
        mean = total / n if n else 0.0
        deviation = max(0.0, squares / n - mean * mean) ** 0.5 if n else 0.0
        if n >= 2 and d > max(floor, mean + width * deviation):
            out.append((first, k))
            first, n, total, squares = k, 0, 0.0, 0.0
        else:
            n, total, squares = n + 1, total + d, squares + d * d
    return [*out, (first, len(frames))]


def payload_of(text: str | None) -> tuple[int, bytes]:
    data = (text or "").encode("utf-8", "replace")
    return len(data), data.ljust(max(1, -(-len(data) // UNIT)) * UNIT)


def files_of(payloads: list[bytes]) -> list[bytes]:
    """An AVI file of each payload; frames are made in groups of bounded size."""
    jobs = [(k, data[i : i + WIDTH * HEIGHT]) for k, data in enumerate(payloads) for i in range(0, len(data), WIDTH * HEIGHT)]
    frames: list[list[bytes]] = [[] for _ in payloads]
    for group in _groups(jobs, lambda j: len(j[1])):
        rows = np.frombuffer(b"".join(x for _, x in group), np.uint8).reshape(-1, WIDTH)
        for (k, _), frame in zip(group, jpeg_frames(rows, [len(x) // WIDTH for _, x in group])):
            frames[k].append(frame)
    return [avi(f) for f in frames]


def samples_of(files: list[bytes]) -> list[tuple[float, list[np.ndarray]]]:
    """Seconds of a frame and decoded frames of each file; frames of many files are decoded together."""
    heads = [read_avi(f) for f in files]
    jobs = [(k, f) for k, (_, frames) in enumerate(heads) for f in frames]
    out: list[tuple[float, list[np.ndarray]]] = [(second, []) for second, _ in heads]
    for group in _groups(jobs, lambda j: len(j[1])):
        for (k, _), x in zip(group, decode_frames([f for _, f in group])):
            out[k][1].append(x)
    return out


def _groups(jobs: list, size) -> Iterator[list]:
    group, total = [], 0
    for job in jobs:
        group.append(job)
        total += size(job)
        if total >= GROUP_BYTES:
            yield group
            group, total = [], 0
    if group:
        yield group


def feature(second: float, frames: list[np.ndarray]) -> str:
    """Shots with their times and mean histograms in thousandths."""
    parts = []
    for a, b in shots(frames):
        share = np.bincount(np.concatenate([f.ravel() for f in frames[a:b]]) >> 4, minlength=BINS)
        share = share * 1000 // max(1, share.sum())
        parts.append(f"{a * second:.2f}-{b * second:.2f}:" + ".".join(map(str, share.tolist())))
    return "|".join(parts)


def store(df: DataFrame, text: str = "text", out: str = "media") -> DataFrame:
    """Adds an AVI file that holds each text's bytes."""

    @F.pandas_udf("binary")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series(files_of([payload_of(t)[1] for t in part]), dtype=object)

    return df.withColumn(out, of(df[text]))


def clips(df: DataFrame, media: str = "media") -> DataFrame:
    """One row for each shot of each file: the other columns, clip, first_frame, frames, start_s, end_s."""

    @F.pandas_udf("array<struct<clip:int,first_frame:int,frames:int,start_s:double,end_s:double>>")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            rows = []
            for data in part:
                try:
                    second, frames = samples_of([data])[0]
                except (ValueError, TypeError, struct.error, KeyError, IndexError):
                    rows.append([])
                    continue
                rows.append([{"clip": k, "first_frame": a, "frames": b - a, "start_s": a * second, "end_s": b * second} for k, (a, b) in enumerate(shots(frames))])
            yield pd.Series(rows)

    keep = [df[c] for c in df.columns if c not in (media, "clip", "first_frame", "frames", "start_s", "end_s")]
    return df.select(*keep, F.inline(of(df[media])))


def digests(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Stores each text, reads the file back and tells what came out."""

    @F.pandas_udf("n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
    def of(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for part in parts:
            rows = []
            for texts in _groups(list(part), lambda t: len(t or "")):
                payloads = [payload_of(t) for t in texts]
                files = files_of([p for _, p in payloads])
                for (n, _), data, (second, frames) in zip(payloads, files, samples_of(files)):
                    back = b"".join(f.tobytes() for f in frames)
                    rows.append((n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-16:]), len(data), hashlib.sha256(data).hexdigest(), feature(second, frames)))
            yield pd.DataFrame(rows, columns=["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return df.select(df[doc_id].alias("doc_id"), of(df[text]).alias("d")).select("doc_id", "d.*")
