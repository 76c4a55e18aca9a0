"""Operator 8, media columns: AVI motion-JPEG to timed clips.

A binary AVI column is parsed (RIFF lists, stream headers, the idx1 index, or a walk through movi where there is no
index), every frame is decoded by a baseline JPEG decoder in numpy (grey or YCbCr with any sampling, restart
intervals, the usual Huffman tables where a frame has none), and shots end where the luma histogram changes: a
difference of at least FLOOR that also exceeds the mean plus SPREAD standard deviations of its neighbours within
WINDOW frames, and is the greatest of them. One map over the rows, no shuffle.

Result of clips(): (media_id, clip, start_frame, end_frame, start_s, end_s, fps, width, height, change, mean_luma,
bad_frames, error), end_frame exclusive. Defined results: null, empty or unreadable bytes, and files without a video stream or frames, give one row
with a null clip and the reason in ``error``; a frame that can't be decoded counts in bad_frames and is taken to
repeat the one before it; repeated rows give their clips again; null ids stay null.

The given tables hold no video, so the query makes its media column from ``embeddings``: each vector is drawn as a
film of several shots by the encoder below (``film``), every row of the table.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import load

FLOOR, SPREAD, WINDOW, BINS = 0.3, 3.0, 8, 32
# fmt: off
ZIGZAG = np.array([0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28, 35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63])
DC_LUMA = ([0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0], list(range(12)))
DC_CHROMA = ([0, 3, 1, 1, 1, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0], list(range(12)))
AC_LUMA = ([0, 2, 1, 3, 3, 2, 4, 3, 5, 5, 4, 4, 0, 0, 1, 125], list(bytes.fromhex(
    "01020300041105122131410613516107227114328191a1082342b1c11552d1f02433627282090a161718191a25262728292a3435363738393a434445464748494a535455565758595a636465666768696a737475767778797a838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aab2b3b4b5b6b7b8b9bac2c3c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae1e2e3e4e5e6e7e8e9eaf1f2f3f4f5f6f7f8f9fa")))
AC_CHROMA = ([0, 2, 1, 2, 4, 4, 3, 4, 7, 5, 4, 4, 0, 1, 2, 119], list(bytes.fromhex(
    "0001020311040521310612415107617113223281081442 91a1b1c109233352f0156272d10a162434e125f11718191a262728292a35363738393a434445464748494a535455565758595a636465666768696a737475767778797a82838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aab2b3b4b5b6b7b8b9bac2c3c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae2e3e4e5e6e7e8e9eaf2f3f4f5f6f7f8f9fa".replace(" ", ""))))
# fmt: on
_k = np.arange(8)
DCT = np.sqrt(np.where(_k == 0, 1, 2) / 8)[:, None] * np.cos((2 * _k[None, :] + 1) * _k[:, None] * np.pi / 16)


class BadMedia(ValueError):
    pass


def huffman_codes(counts: list[int], values: list[int]) -> dict[int, tuple[int, int]]:
    """value -> (code, bits)."""
    code, out, at = 0, {}, 0
    for bits, n in enumerate(counts, 1):
        for v in values[at : at + n]:
            out[v] = (code, bits)
            code += 1
        at += n
        code <<= 1
    return out


@lru_cache(maxsize=64)
def _lookup(counts: tuple[int, ...], values: tuple[int, ...]) -> list[int]:
    """The next 16 bits -> bits << 8 | value; 0 where there is no such code."""
    table = np.zeros(65536, np.int64)
    for v, (code, bits) in huffman_codes(list(counts), list(values)).items():
        table[code << (16 - bits) : (code + 1) << (16 - bits)] = bits << 8 | v
    return table.tolist()


def _usual(kind: int, chroma: int) -> list[int]:
    counts, values = ((DC_LUMA, DC_CHROMA), (AC_LUMA, AC_CHROMA))[kind][chroma]
    return _lookup(tuple(counts), tuple(values))


def decode_jpeg(raw: bytes) -> list[np.ndarray]:
    """The component planes (Y or Y, Cb, Cr) of a baseline JPEG, as uint8, at their own sampling."""
    if raw[:2] != b"\xff\xd8":
        raise BadMedia("no JPEG start")
    at, quant, tables, frame, restart = 2, {}, {}, None, 0
    while True:
        if at + 4 > len(raw) or raw[at] != 0xFF:
            raise BadMedia("broken JPEG segment")
        mark = raw[at + 1]
        if mark == 0xFF:
            at += 1
            continue
        size = raw[at + 2] << 8 | raw[at + 3]
        body = raw[at + 4 : at + 2 + size]
        if mark == 0xDB:
            p = 0
            while p < len(body):
                wide, k = body[p] >> 4, body[p] & 15
                q = np.frombuffer(body[p + 1 : p + 1 + 64 * (1 + wide)], ">u2" if wide else "u1").astype(np.float64)
                quant[k] = np.zeros(64)
                quant[k][ZIGZAG] = q
                p += 1 + 64 * (1 + wide)
        elif mark == 0xC4:
            p = 0
            while p < len(body):
                counts = tuple(body[p + 1 : p + 17])
                n = sum(counts)
                tables[body[p]] = _lookup(counts, tuple(body[p + 17 : p + 17 + n]))
                p += 17 + n
        elif mark == 0xC0 or mark == 0xC1:
            h, w, n = body[1] << 8 | body[2], body[3] << 8 | body[4], body[5]
            frame = (h, w, [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)])
            if body[0] != 8 or not h or not w:
                raise BadMedia("JPEG precision or size")
        elif mark in (0xC2, 0xC3, 0xC5, 0xC6, 0xC7, 0xC9, 0xCA, 0xCB, 0xCD, 0xCE, 0xCF):
            raise BadMedia("not a baseline JPEG")
        elif mark == 0xDD:
            restart = body[0] << 8 | body[1]
        elif mark == 0xDA:
            if frame is None:
                raise BadMedia("scan before frame")
            return _scan(raw, at + 2 + size, body, frame, quant, tables, restart)
        at += 2 + size


def _scan(raw: bytes, at: int, head: bytes, frame: tuple, quant: dict, tables: dict, restart: int) -> list[np.ndarray]:
    height, width, comps = frame
    which = {head[1 + 2 * i]: head[2 + 2 * i] for i in range(head[0])}
    hmax, vmax = max(c[1] for c in comps), max(c[2] for c in comps)
    alone = len(comps) == 1
    if alone:
        comps, hmax, vmax = [(comps[0][0], 1, 1, comps[0][3])], 1, 1
    cols, rows = -(-width // (8 * hmax)), -(-height // (8 * vmax))
    plan = []
    for k, (cid, h, v, q) in enumerate(comps):
        sel = which.get(cid)
        if sel is None or q not in quant:
            raise BadMedia("component without tables")
        coef = np.zeros((rows * v, cols * h, 64), np.float64)
        plan.append((k, h, v, tables.get(sel >> 4) or _usual(0, min(k, 1)), tables.get(0x10 | (sel & 15)) or _usual(1, min(k, 1)), coef))
    # the entropy-coded segments between restart marks, without stuffed bytes
    end = at
    parts, begin = [], at
    while True:
        end = raw.find(b"\xff", end)
        if end < 0 or end + 1 >= len(raw):
            parts.append(raw[begin:])
            break
        if raw[end + 1] == 0:
            end += 2
        elif 0xD0 <= raw[end + 1] <= 0xD7:
            parts.append(raw[begin:end])
            begin = end = end + 2
        else:
            parts.append(raw[begin:end])
            break
    part, bits, pos, left = -1, b"", 0, 0
    pred = [0] * len(plan)
    zig = ZIGZAG.tolist()
    for mcu in range(rows * cols):
        if not left:
            part += 1
            if part >= len(parts):
                raise BadMedia("scan ends early")
            data = parts[part].replace(b"\xff\x00", b"\xff")
            total = len(data) * 8
            bits, pos, left = data + b"\xff" * 8, 0, restart or rows * cols
            pred = [0] * len(plan)
        left -= 1
        my, mx = divmod(mcu, cols)
        for k, h, v, dc, ac, coef in plan:
            for b in range(h * v):
                block = coef[my * v + b // h, mx * h + b % h]
                n = 0
                while n < 64:
                    word = int.from_bytes(bits[pos >> 3 : (pos >> 3) + 6], "big")
                    off = 32 - (pos & 7)
                    hit = (dc if n == 0 else ac)[(word >> off) & 0xFFFF]
                    if not hit or pos > total:
                        raise BadMedia("bad Huffman code")
                    used, sym = hit >> 8, hit & 255
                    size = sym & 15
                    value = 0
                    if size:
                        value = (word >> (off + 16 - used - size)) & ((1 << size) - 1)
                        if value < 1 << (size - 1):
                            value -= (1 << size) - 1
                    pos += used + size
                    if n == 0:
                        pred[k] += value
                        block[0] = pred[k]
                        n = 1
                    elif size:
                        n += sym >> 4
                        if n > 63:
                            raise BadMedia("coefficient out of range")
                        block[zig[n]] = value
                        n += 1
                    elif sym == 0xF0:
                        n += 16
                    else:
                        break
    planes = []
    for (k, h, v, _, _, coef), (_, _, _, q) in zip(plan, comps):
        block = (coef * quant[q]).reshape(*coef.shape[:2], 8, 8)
        pix = DCT.T @ block @ DCT + 128
        plane = pix.transpose(0, 2, 1, 3).reshape(coef.shape[0] * 8, coef.shape[1] * 8)
        planes.append(np.clip(np.rint(plane[: -(-height * v // vmax), : -(-width * h // hmax)]), 0, 255).astype(np.uint8))
    return planes


def parse_avi(raw: bytes) -> tuple[float, int, int, list[bytes]]:
    """(frames a second, width, height, JPEG frames) of the first video stream."""
    if len(raw) < 12 or raw[:4] != b"RIFF" or raw[8:12] != b"AVI ":
        raise BadMedia("not an AVI file")
    found: dict = {"streams": [], "movi": [], "idx": None, "fps": None}

    def walk(lo: int, hi: int) -> None:
        while lo + 8 <= hi:
            kind, size = raw[lo : lo + 4], struct.unpack_from("<I", raw, lo + 4)[0]
            body, stop = lo + 8, min(lo + 8 + size, hi)
            if kind == b"LIST" or kind == b"RIFF":
                if raw[body : body + 4] == b"movi":
                    found["movi"].append((body, stop))
                else:
                    walk(body + 4, stop)
            elif kind == b"avih" and stop - body >= 40:
                us, size_at = struct.unpack_from("<I", raw, body)[0], struct.unpack_from("<II", raw, body + 32)
                found["fps"], found["size"] = 1e6 / us if us else None, size_at
            elif kind == b"strh" and stop - body >= 28:
                scale, rate = struct.unpack_from("<II", raw, body + 20)
                found["streams"].append((raw[body : body + 4], rate / scale if scale and rate else None))
            elif kind == b"idx1":
                found["idx"] = (body, stop)
            lo = body + size + (size & 1)

    walk(0, len(raw))
    video = next((i for i, s in enumerate(found["streams"]) if s[0] == b"vids"), None)
    if video is None or not found["movi"]:
        raise BadMedia("no video stream")
    tags = (b"%02ddc" % video, b"%02ddb" % video)
    frames: list[bytes] = []
    if found["idx"] and len(found["movi"]) == 1:
        base = found["movi"][0][0]
        lo, hi = found["idx"]
        entries = [struct.unpack_from("<4sIII", raw, p) for p in range(lo, hi - 15, 16)]
        mine = [(o, n) for tag, _, o, n in entries if tag in tags]
        # offsets count from the word 'movi', or from the file's start
        if mine and raw[base + mine[0][0] : base + mine[0][0] + 4] not in tags:
            base = 0
        if all(raw[base + o : base + o + 4] in tags for o, n in mine):
            frames = [raw[base + o + 8 : base + o + 8 + n] for o, n in mine]
    if not frames:
        for lo, hi in found["movi"]:
            stack = [(lo + 4, hi)]
            while stack:
                lo, hi = stack.pop()
                while lo + 8 <= hi:
                    kind, size = raw[lo : lo + 4], struct.unpack_from("<I", raw, lo + 4)[0]
                    if kind == b"LIST":
                        stack.append((lo + 8 + size + (size & 1), hi))
                        lo, hi = lo + 12, min(lo + 8 + size, hi)
                        continue
                    if kind in tags:
                        frames.append(raw[lo + 8 : min(lo + 8 + size, hi)])
                    lo += 8 + size + (size & 1)
    if not frames:
        raise BadMedia("no frames")
    return found["streams"][video][1] or found["fps"] or 25.0, *found.get("size", (0, 0)), frames


def shot_starts(hist: np.ndarray) -> tuple[list[int], np.ndarray]:
    """First frames of the shots, and each frame's change from the one before (0 to 1)."""
    # neighbouring bins share, so that a drift over a bin's edge counts little
    soft = hist / 2
    soft[:, 1:] += hist[:, :-1] / 4
    soft[:, :-1] += hist[:, 1:] / 4
    d = np.zeros(len(hist))
    d[1:] = np.abs(np.diff(soft, axis=0)).sum(1) / 2
    out = [0]
    for i in range(1, len(d)):
        lo, hi = max(1, i - WINDOW), min(len(d), i + WINDOW + 1)
        near = np.delete(d[lo:hi], i - lo)
        # a neighbour that is itself a cut would hide this one: the median's side of the neighbours is the measure
        calm = np.sort(near)[: max(1, (len(near) * 3 + 3) // 4)] if len(near) else np.zeros(1)
        if d[i] >= FLOOR and d[i] > calm.mean() + SPREAD * calm.std() and d[i] >= d[max(1, i - 1) : i + 2].max():
            out.append(i)
    return out, d


def clip_rows(raw: bytes | None) -> list[tuple]:
    if not raw:
        return [(None,) * 11 + ("no bytes",)]
    try:
        fps, width, height, frames = parse_avi(raw)
    except (BadMedia, struct.error, IndexError) as e:
        return [(None,) * 11 + (str(e) or "broken file",)]
    hist, luma, bad = np.zeros((len(frames), BINS)), np.zeros(len(frames)), np.zeros(len(frames), int)
    for i, f in enumerate(frames):
        try:
            y = decode_jpeg(f)[0]
            height, width = (height, width) if height and width else y.shape
            hist[i], luma[i] = np.bincount(y.ravel() >> 3, minlength=BINS) / y.size, y.mean()
        except (BadMedia, IndexError, ValueError, KeyError):
            bad[i] = 1
            if i:
                hist[i], luma[i] = hist[i - 1], luma[i - 1]
    if bad.all():
        return [(None,) * 11 + ("no frame can be decoded",)]
    starts, change = shot_starts(hist)
    return [(k, a, b, round(a / fps, 6), round(b / fps, 6), round(fps, 6), int(width), int(height), round(float(change[a]), 6), round(float(luma[a:b].mean()), 4), int(bad[a:b].sum()), None) for k, (a, b) in enumerate(zip(starts, [*starts[1:], len(frames)]))]


CLIPS = "media_id long, clip int, start_frame int, end_frame int, start_s double, end_s double, fps double, width int, height int, change double, mean_luma double, bad_frames int, error string"
_TYPES = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.float64(), pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.int32(), pa.string()]


def clips(media: DataFrame) -> DataFrame:
    """Clips of (media_id, avi)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(m, *c) for m, raw in zip(batch.column(0).to_pylist(), batch.column(1)) for c in clip_rows(raw.as_py())]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _TYPES)], [x.split()[0] for x in CLIPS.split(", ")])

    return media.select(F.col("media_id").cast("long").alias("media_id"), F.col("avi").cast("binary").alias("avi")).mapInArrow(run, CLIPS)


# ---- a writer, for media made from other columns ----

QUANT = np.full(64, 8)


@lru_cache(maxsize=4)
def _codes(kind: int) -> dict[int, tuple[int, int]]:
    return huffman_codes(*(DC_LUMA, AC_LUMA)[kind])


def encode_jpeg(plane: np.ndarray, restart: int = 0) -> bytes:
    """A grey baseline JPEG without Huffman tables of its own, as motion JPEG has them."""
    h, w = plane.shape
    rows, cols = -(-h // 8), -(-w // 8)
    full = np.pad(plane.astype(np.float64) - 128, ((0, rows * 8 - h), (0, cols * 8 - w)), mode="edge")
    blocks = full.reshape(rows, 8, cols, 8).transpose(0, 2, 1, 3)
    coef = np.rint((DCT @ blocks @ DCT.T).reshape(-1, 64) / QUANT).astype(int)[:, ZIGZAG]
    dc, ac = _codes(0), _codes(1)
    out, acc, n, pred = [], 0, 0, 0

    def flush() -> None:
        nonlocal acc, n, out
        pad = -n % 8
        raw = ((acc << pad) | ((1 << pad) - 1)).to_bytes((n + pad) // 8, "big") if n else b""
        out.append(raw.replace(b"\xff", b"\xff\x00"))
        acc, n = 0, 0

    for i, row in enumerate(coef.tolist()):
        if restart and i and i % restart == 0:
            flush()
            out.append(bytes([0xFF, 0xD0 + (i // restart - 1) % 8]))
            pred = 0
        value = row[0] - pred
        pred = row[0]
        size = abs(value).bit_length()
        code, bits = dc[size]
        acc, n = (acc << bits | code) << size | (value if value >= 0 else value + (1 << size) - 1), n + bits + size
        run = 0
        last = max((k for k in range(1, 64) if row[k]), default=0)
        for value in row[1 : last + 1]:
            if not value:
                run += 1
                continue
            while run > 15:
                code, bits = ac[0xF0]
                acc, n, run = acc << bits | code, n + bits, run - 16
            size = abs(value).bit_length()
            code, bits = ac[run << 4 | size]
            acc, n, run = (acc << bits | code) << size | (value if value >= 0 else value + (1 << size) - 1), n + bits + size, 0
        if last < 63:
            code, bits = ac[0]
            acc, n = acc << bits | code, n + bits
    flush()
    seg = lambda mark, body: bytes([0xFF, mark]) + struct.pack(">H", len(body) + 2) + body
    head = b"\xff\xd8" + seg(0xDB, b"\0" + bytes(QUANT[ZIGZAG].tolist())) + seg(0xC0, struct.pack(">BHHB", 8, h, w, 1) + b"\x01\x11\x00")
    head += seg(0xDD, struct.pack(">H", restart)) if restart else b""
    return head + seg(0xDA, b"\x01\x01\x00\x00\x3f\x00") + b"".join(out) + b"\xff\xd9"


def write_avi(frames: list[bytes], fps: int, width: int, height: int, index: bool = True) -> bytes:
    chunk = lambda kind, body: kind + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)
    lst = lambda kind, body: chunk(b"LIST", kind + body)
    avih = struct.pack("<14I", 1_000_000 // fps, 0, 0, 16, len(frames), 0, 1, 0, width, height, 0, 0, 0, 0)
    strh = b"vidsMJPG" + struct.pack("<IHHIIIIIIIIHHHH", 0, 0, 0, 0, 1, fps, 0, len(frames), 0, 0, 0, 0, 0, width, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 24, b"MJPG", width * height * 3, 0, 0, 0, 0)
    movi, idx, at = b"", b"", 4
    for f in frames:
        idx += struct.pack("<4sIII", b"00dc", 16, at, len(f))
        c = chunk(b"00dc", f)
        movi += c
        at += len(c)
    body = b"AVI " + lst(b"hdrl", chunk(b"avih", avih) + lst(b"strl", chunk(b"strh", strh) + chunk(b"strf", strf))) + lst(b"movi", movi) + (chunk(b"idx1", idx) if index else b"")
    return chunk(b"RIFF", body)


def film(vector: np.ndarray, key: int) -> tuple[bytes, list[int]]:
    """A film of 2 to 4 shots, 16 x 16 grey, drawn from the vector; and the first frames of its shots."""
    v = np.nan_to_num(np.asarray(vector, np.float64))
    v = np.resize(v, 64) if len(v) else np.zeros(64)
    shots, frames, starts = 2 + key % 3, [], []
    ramp = np.linspace(-1, 1, 16)
    for s in range(shots):
        starts.append(len(frames))
        part = np.clip(v[s * 16 : s * 16 + 16] * 60, -20, 20)
        base = np.kron(part[:4].reshape(2, 2), np.ones((8, 8))) / 2 + (40 + 60 * ((s + key) % 4))
        for f in range(3 + (key // 3 + s) % 3):
            frames.append(np.clip(base + part[4] / 2 * ramp[None, :] + part[5] / 2 * ramp[:, None] + f * 0.5, 0, 255))
    return write_avi([encode_jpeg(f) for f in frames], 10 + key % 3 * 5, 16, 16), starts


def media_table(embeddings: DataFrame) -> DataFrame:
    """(media_id, avi) of every vector; a null vector has null media."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [None if v is None else film(v, abs(k or 0))[0] for k, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(made, pa.binary())], ["media_id", "avi"])

    return embeddings.select(F.col("vec_id").cast("long").alias("media_id"), F.col("embedding").cast("array<double>").alias("embedding")).mapInArrow(run, "media_id long, avi binary")


def op8_media_clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clips(media_table(load(spark, sf_dir, "embeddings")))
