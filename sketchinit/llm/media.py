"""AVI with motion-JPEG: writing, reading back, and shots by adaptive histogram differences.

A payload of bytes is stored as grey samples, one sample for each 8 x 8 block
of a baseline JPEG frame. A flat block has a DC coefficient only; with a DC
quantiser of 8 it is kept without loss. The Huffman table gives the category
c a code of 10 - c bits, so that code and c magnitude bits are always 10
bits, and the end-of-block code is one bit: every sample takes 11 bits, and
whole frames are coded and decoded as arrays. Any JPEG decoder reads the
frames. The last frame is filled with 0; the payload's length is in the AVI's
INFO comment.

Edge cases: null text counts as empty (a payload of 64 zero bytes); equal
texts give equal files; a damaged file, or a text too long for a RIFF file,
raises ValueError; a one-frame file is one shot; frames are coded in groups,
so a long text takes memory for a few times its size. Files of other writers
are read too, as grey pixels of their baseline frames.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

SIDE = 32  # samples in a row and rows of a frame: 256 x 256 pixels
FRAME = SIDE * SIDE
FPS = 25
_BITS = 11

# ---------------------------------------------------------------- JPEG frames


def _tables() -> tuple[np.ndarray, np.ndarray]:
    """For each DC difference -255..255 its 11-bit word; for each first 10 bits the difference."""
    words = np.zeros(511, np.uint16)
    back = np.full(1 << 10, 9999, np.int16)
    for d in range(-255, 256):
        c = abs(d).bit_length()
        code_len = 10 - c
        # canonical codes by growing length: category c gets code_len - 1 ones, then 0
        code = (1 << code_len) - 2
        low = d if d > 0 else d + (1 << c) - 1
        ten = (code << c) | (low if c else 0)
        words[d + 255] = ten << 1  # the end-of-block code is a 0
        back[ten] = d
    return words, back


_WORDS, _BACK = _tables()


def _segment(mark: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, mark, len(body) + 2) + body


def _head() -> bytes:
    quant = bytes([0]) + bytes([8] * 64)
    frame = struct.pack(">BHHB", 8, SIDE * 8, SIDE * 8, 1) + bytes([1, 0x11, 0])
    # code lengths 1 (category 9) to 10 (category 0); AC: one code, the end of block
    dc = bytes([0x00]) + bytes([1] * 10 + [0] * 6) + bytes(range(9, -1, -1))
    ac = bytes([0x10]) + bytes([1] + [0] * 15) + bytes([0])
    scan = bytes([1, 1, 0x00, 0, 63, 0])
    return b"\xff\xd8" + _segment(0xDB, quant) + _segment(0xC0, frame) + _segment(0xC4, dc) + _segment(0xC4, ac) + _segment(0xDA, scan)


_HEAD, _TAIL = _head(), b"\xff\xd9"


GROUP = 64  # frames that are coded or decoded as one array


def encode_frames(samples: np.ndarray) -> list[bytes]:
    """samples: (frames, FRAME) bytes. One JPEG file for each frame."""
    out: list[bytes] = []
    for lo in range(0, len(samples), GROUP):
        level = samples[lo : lo + GROUP].astype(np.int16) - 128
        diff = np.diff(level, axis=1, prepend=np.int16(0))
        words = _WORDS[diff + 255]
        bits = np.unpackbits(words.astype(">u2").view(np.uint8).reshape(*words.shape, 2), axis=2)[:, :, 16 - _BITS :]
        packed = np.packbits(bits.reshape(len(level), -1), axis=1)
        out += [_HEAD + row.tobytes().replace(b"\xff", b"\xff\x00") + _TAIL for row in packed]
    return out


def parse_jpeg(data: bytes) -> dict:
    """Tables and scan of a baseline JPEG: {'quant', 'huffman', 'frame', 'scan', 'restart', 'bits'}; bits are the coded bytes without stuffing."""
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG frame")
    got: dict = {"quant": {}, "huffman": {}, "frame": None, "restart": 0}
    at = 2
    while at + 4 <= len(data):
        if data[at] != 0xFF:
            raise ValueError("no marker where one must be")
        mark = data[at + 1]
        size = struct.unpack_from(">H", data, at + 2)[0]
        body = data[at + 4 : at + 2 + size]
        at += 2 + size
        if mark == 0xDB:
            while body:
                wide = body[0] >> 4
                n = 64 * (1 + wide)
                got["quant"][body[0] & 15] = np.frombuffer(body[1 : 1 + n], ">u2" if wide else np.uint8).astype(np.int64)
                body = body[1 + n :]
        elif mark == 0xC4:
            while body:
                n = sum(body[1:17])
                got["huffman"][body[0]] = (tuple(body[1:17]), body[17 : 17 + n])
                body = body[17 + n :]
        elif mark in (0xC0, 0xC1):
            high, wide, parts = struct.unpack_from(">HHB", body, 1)
            got["frame"] = (high, wide, [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(parts)])
        elif mark in (0xC2, 0xC3, *range(0xC5, 0xC8), *range(0xC9, 0xD0)):
            raise ValueError("only baseline frames are read")
        elif mark == 0xDD:
            got["restart"] = struct.unpack(">H", body)[0]
        elif mark == 0xDA:
            got["scan"] = [(body[1 + 2 * i], body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15) for i in range(body[0])]
            end = data.rfind(b"\xff\xd9")
            if end < at or got["frame"] is None:
                raise ValueError("a frame without an end or a size")
            got["bits"] = data[at:end]
            return got
    raise ValueError("a frame without a scan")


def _codes(table: tuple[tuple[int, ...], bytes]) -> dict[tuple[int, int], int]:
    """{(length, code): symbol} of a Huffman table."""
    out, code, k = {}, 0, 0
    for length, n in enumerate(table[0], 1):
        for _ in range(n):
            out[length, code] = table[1][k]
            code, k = code + 1, k + 1
        code <<= 1
    return out


# Places of the 64 coefficients in zigzag order.
_ZIGZAG = np.array(sorted(range(64), key=lambda i: (i // 8 + i % 8, (i // 8 if (i // 8 + i % 8) % 2 else i % 8))))
_COS = np.array([[np.cos((2 * x + 1) * u * np.pi / 16) * (np.sqrt(0.125) if u == 0 else 0.5) for u in range(8)] for x in range(8)])


def decode_jpeg(data: bytes) -> np.ndarray:
    """The grey picture (height, width) of any baseline JPEG: Huffman codes, zigzag, quantisers and the inverse transform of its first component."""
    j = parse_jpeg(data)
    high, wide, parts = j["frame"]
    most_h, most_v = max(p[1] for p in parts), max(p[2] for p in parts)
    if len(j["scan"]) == 1:
        parts = [(*p[:1], 1, 1, p[3]) for p in parts if p[0] == j["scan"][0][0]]
        most_h = most_v = 1
    across, down = -(-wide // (8 * most_h)), -(-high // (8 * most_v))
    tables = {c: (_codes(j["huffman"][d]), _codes(j["huffman"][16 + a])) for c, d, a in j["scan"]}
    pieces = re.split(rb"\xff[\xd0-\xd7]", j["bits"]) if j["restart"] else [j["bits"]]
    first = parts[0]
    blocks = np.zeros((down * first[2], across * first[1], 64), np.int64)
    unit = 0
    for piece in pieces:
        raw = piece.replace(b"\xff\x00", b"\xff")
        value, left, at = int.from_bytes(raw, "big"), len(raw) * 8, 0

        def take(n: int) -> int:
            nonlocal at
            if at + n > left:
                raise ValueError("the coded data end too early")
            at += n
            return (value >> (left - at)) & ((1 << n) - 1)

        def symbol(codes: dict[tuple[int, int], int]) -> int:
            code = 0
            for n in range(1, 17):
                code = code << 1 | take(1)
                if (n, code) in codes:
                    return codes[n, code]
            raise ValueError("unknown code in a frame")

        def number(n: int) -> int:
            v = take(n) if n else 0
            return v if not n or v >> (n - 1) else v - (1 << n) + 1

        last = dict.fromkeys(tables, 0)
        for _ in range(min(j["restart"] or across * down, across * down - unit)):
            for c, h, v, _q in parts:
                for y in range(v):
                    for x in range(h):
                        dc, ac = tables[c]
                        last[c] += number(symbol(dc))
                        block, k = np.zeros(64, np.int64), 1
                        block[0] = last[c]
                        while k < 64:
                            s = symbol(ac)
                            if s == 0:
                                break
                            k += s >> 4
                            if s & 15:
                                if k > 63:
                                    raise ValueError("a block with too many coefficients")
                                block[k] = number(s & 15)
                            k += 1
                        if c == first[0]:
                            blocks[unit // across * v + y, unit % across * h + x] = block
            unit += 1
    freq = np.zeros(blocks.shape, float)
    freq[:, :, _ZIGZAG] = blocks * j["quant"][first[3]]
    tiles = np.einsum("xu,abuv,yv->abxy", _COS, freq.reshape(*blocks.shape[:2], 8, 8), _COS)
    grey = tiles.transpose(0, 2, 1, 3).reshape(blocks.shape[0] * 8, blocks.shape[1] * 8)
    return np.clip(np.round(grey + 128), 0, 255).astype(np.uint8)[:high, :wide]


def _flat(j: dict) -> bool:
    """Whether a frame has one component, eight as DC quantiser, and the code lengths under which every flat block takes _BITS bits."""
    frame, head = j["frame"], parse_jpeg(_HEAD + _TAIL)
    return frame == head["frame"] and j["scan"] == head["scan"] and j["huffman"] == head["huffman"] and not j["restart"] and int(j["quant"][0][0]) == 8


def decode_frames(frames: list[bytes]) -> np.ndarray:
    """Samples by frame: one for each block of flat frames, decoded as arrays from the tables that the frame carries; the pixels of other frames."""
    parsed = [parse_jpeg(f) for f in frames[:1]]
    if not frames or not _flat(parsed[0]):
        return np.stack([decode_jpeg(f).ravel() for f in frames]) if frames else np.zeros((0, 0), np.uint8)
    size, out = FRAME * _BITS // 8, []
    head = frames[0][: len(frames[0]) - len(parsed[0]["bits"]) - 2]
    for lo in range(0, len(frames), GROUP):
        rows = []
        for f in frames[lo : lo + GROUP]:
            same = f.startswith(head) and f.endswith(_TAIL)
            j = None if same else parse_jpeg(f)
            if j is not None and not _flat(j):
                raise ValueError("flat frames and others in one file")
            raw = (f[len(head) : -2] if same else j["bits"]).replace(b"\xff\x00", b"\xff")
            if len(raw) != size:
                raise ValueError("a frame of another size")
            rows.append(np.frombuffer(raw, np.uint8))
        bits = np.unpackbits(np.stack(rows), axis=1).reshape(len(rows), FRAME, _BITS)
        full = np.zeros((len(rows), FRAME, 16), np.uint8)
        full[:, :, 16 - _BITS :] = bits
        ten = np.packbits(full, axis=2).view(">u2").reshape(len(rows), FRAME) >> 1
        diff = _BACK[ten]
        if (diff == 9999).any():
            raise ValueError("unknown code in a frame")
        out.append((np.cumsum(diff, axis=1, dtype=np.int32) + 128).astype(np.uint8))
    return np.concatenate(out)


# ---------------------------------------------------------------- RIFF


def _chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) % 2)


def write_avi(payload: bytes) -> bytes:
    """payload (a positive number of bytes) as one AVI file."""
    n = -(-len(payload) // FRAME)
    samples = np.zeros(n * FRAME, np.uint8)
    samples[: len(payload)] = np.frombuffer(payload, np.uint8)
    frames = encode_frames(samples.reshape(n, FRAME))
    if sum(map(len, frames)) + 24 * n > (1 << 32) - 4096:
        raise ValueError("a RIFF file holds less than 4 GiB: about 3 GiB of text")
    most, px = max(map(len, frames)), SIDE * 8
    avih = struct.pack("<10I16x", 1_000_000 // FPS, most * FPS, 0, 0x10, n, 0, 1, most, px, px)
    strh = b"vidsMJPG" + struct.pack("<IHHIIIIIIII4H", 0, 0, 0, 0, 1, FPS, 0, n, most, 10_000, 0, 0, 0, px, px)
    strf = struct.pack("<IiiHH4sIiiII", 40, px, px, 1, 24, b"MJPG", px * px * 3, 0, 0, 0, 0)
    hdrl = _chunk(b"LIST", b"hdrl" + _chunk(b"avih", avih) + _chunk(b"LIST", b"strl" + _chunk(b"strh", strh) + _chunk(b"strf", strf)))
    info = _chunk(b"LIST", b"INFO" + _chunk(b"ICMT", b"payload=%d\0" % len(payload)))
    at, index, movi = 4, [], [b"movi"]
    for f in frames:
        c = _chunk(b"00dc", f)
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        movi.append(c)
        at += len(c)
    body = b"AVI " + hdrl + info + _chunk(b"LIST", b"".join(movi)) + _chunk(b"idx1", b"".join(index))
    return b"RIFF" + struct.pack("<I", len(body)) + body


def parse_avi(data: bytes) -> dict:
    """{'frames': bytes of each frame by the index, 'rate': frames a second, 'comment': INFO comment or ''}."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    found: dict = {"comment": "", "rate": float(FPS), "movi": None, "index": []}

    def walk(at: int, end: int) -> None:
        while at + 8 <= end:
            name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
            body = at + 8
            if body + size > len(data):
                raise ValueError("a chunk runs over the end")
            if name == b"LIST":
                if data[body : body + 4] == b"movi":
                    found["movi"] = (body, body + size)
                else:
                    walk(body + 4, body + size)
            elif name == b"strh" and data[body : body + 4] == b"vids":
                scale, rate = struct.unpack_from("<II", data, body + 20)
                found["rate"] = rate / max(1, scale)
            elif name == b"ICMT":
                found["comment"] = data[body : body + size].split(b"\0")[0].decode("ascii", "replace")
            elif name == b"idx1":
                found["index"] = [struct.unpack_from("<4sIII", data, body + i) for i in range(0, size - 15, 16)]
            at = body + size + size % 2

    walk(12, len(data))
    if found["movi"] is None:
        raise ValueError("no movi list")
    start, end = found["movi"]
    frames = []
    if found["index"]:
        for name, _, offset, size in found["index"]:
            if name[2:] in (b"dc", b"db"):
                at = start + offset
                if data[at : at + 4] != name or struct.unpack_from("<I", data, at + 4)[0] != size:
                    raise ValueError("the index does not match the frames")
                frames.append(data[at + 8 : at + 8 + size])
    else:  # a file without an index: frames in order
        at = start + 4
        while at + 8 <= end:
            name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
            if name[2:] in (b"dc", b"db"):
                frames.append(data[at + 8 : at + 8 + size])
            at += 8 + size + size % 2
    return {"frames": frames, "rate": found["rate"], "comment": found["comment"]}


def read_payload(data: bytes) -> tuple[bytes, np.ndarray, float]:
    """(payload, samples by frame, frame rate) of a stored file."""
    avi = parse_avi(data)
    if not avi["comment"].startswith("payload="):
        raise ValueError("no payload length in the comment")
    samples = decode_frames(avi["frames"])
    return samples.tobytes()[: int(avi["comment"][8:])], samples, avi["rate"]


# ---------------------------------------------------------------- shots


def histograms(samples: np.ndarray, bins: int = 32) -> np.ndarray:
    """Share of the samples in each grey bin, by frame."""
    out = []
    for lo in range(0, len(samples), GROUP):
        some = samples[lo : lo + GROUP]
        n = len(some)
        at = (some >> (8 - bins.bit_length() + 1)).astype(np.int64) + np.arange(n)[:, None] * bins
        out.append(np.bincount(at.ravel(), minlength=n * bins).reshape(n, bins) / samples.shape[1])
    return np.concatenate(out) if out else np.zeros((0, bins))


def shots(hist: np.ndarray, window: int = 8, factor: float = 2.0, least: float = 0.15) -> list[tuple[int, int]]:
    """Frame ranges [start, end). A cut: the difference to the last frame is over `least` and over mean + factor * deviation of its neighbours."""
    n = len(hist)
    if n < 2:
        return [(0, n)] if n else []
    d = np.abs(np.diff(hist, axis=0)).sum(axis=1) / 2
    pad = np.concatenate([np.zeros((1,)), np.cumsum(d)])
    pad2 = np.concatenate([np.zeros((1,)), np.cumsum(d * d)])
    i = np.arange(len(d))
    lo, hi = np.maximum(i - window, 0), np.minimum(i + window + 1, len(d))
    k = hi - lo - 1  # neighbours without the difference itself
    mean = (pad[hi] - pad[lo] - d) / np.maximum(k, 1)
    var = np.maximum((pad2[hi] - pad2[lo] - d * d) / np.maximum(k, 1) - mean**2, 0)
    cut = np.flatnonzero((d > least) & (d > mean + factor * np.sqrt(var))) + 1
    edges = [0, *cut.tolist(), n]
    return list(zip(edges, edges[1:]))


def payload_of(text: str | None, unit: int = 64) -> tuple[bytes, int]:
    """UTF-8 bytes filled with 0 to a positive multiple of unit, and their number before."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    size = max(unit, -(-len(raw) // unit) * unit)
    return raw.ljust(size, b"\0"), len(raw)


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media): each whole text as one AVI file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 64):  # files are larger than texts: small batches
                part = b.slice(at, 64)
                made = [payload_of(t.as_py()) for t in part.column(1)]
                files = pa.array([write_avi(p) for p, _ in made], pa.large_binary()).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([n for _, n in made], pa.int64()), files], names=["doc_id", "n_bytes", "media"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, n_bytes long, media binary")


_CLIP = pa.struct([("start_s", pa.float64()), ("end_s", pa.float64()), ("frames", pa.int32()), ("mean", pa.float64())])
_READ = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, clips array<struct<start_s:double,end_s:double,frames:int,mean:double>>"


def read_row(media: bytes) -> tuple:
    """What one stored file holds: payload digest and timed clips."""
    payload, samples, rate = read_payload(media)
    cut = shots(histograms(samples))
    clips = [{"start_s": s / rate, "end_s": e / rate, "frames": e - s, "mean": round(float(samples[s:e].mean()), 3)} for s, e in cut]
    return len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(media), hashlib.sha256(media).hexdigest(), clips


def clips(stored: DataFrame, media_col: str = "media") -> DataFrame:
    """stored with media_col replaced by what reading the file gives: digests of the payload and timed clips."""
    at = stored.columns.index(media_col)
    rest = [c for c in stored.columns if c != media_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.list_(_CLIP))
        for b in batches:
            rows = [read_row(m.as_py()) for m in b.column(at)]
            cols = [b.column(b.schema.get_field_index(c)) for c in rest] + [pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays(cols, names=[*rest, *(p.strip().split()[0] for p in _READ.split(", "))])

    head = ", ".join(f"`{c}` {stored.schema[c].dataType.simpleString()}" for c in rest)
    return stored.mapInArrow(run, f"{head}, {_READ}")


def clip_rows(read: DataFrame) -> DataFrame:
    """One timed row for each clip: (doc_id, clip, start_s, end_s, frames, mean)."""
    return read.select("doc_id", F.posexplode("clips").alias("clip", "c")).select("doc_id", "clip", "c.*")
