"""Media columns: AVI with motion JPEG, written and read without loss, and shots found from histogram differences.

Storing bytes as pictures: each payload byte is one 8x8 block of a grey baseline JPEG whose only coefficient is the
block's mean. With a quantiser of 8 the mean is kept exactly, so every decoder shows the byte as the block's grey
value. The Huffman table gives a difference of category c a code of 9 - c bits, so each block takes 10 bits (with the
end-of-block bit) and coding and decoding are array operations; other frames go through the general decoder: baseline
JPEG, grey or colour, any sampling factors, restarts, one scan or several, and the standard's Huffman tables where a frame brings none (as
motion JPEG mostly does).

Reading: the RIFF tree is parsed (several RIFF parts too), frames of the first video stream are found through the OpenDML index,
else the idx1 index, else the movi list; each intra frame is decoded, and a cut is set where the histogram difference of
neighbouring frames' luminance stands out against the running mean and spread of those before it. Shots become timed clip rows.

Edge cases: null text is empty; the payload is padded with zeros to a positive multiple of 64 and its length is stored in
the file; equal texts give equal bytes; very long texts only add frames; rows are kept one by one, repeated ids and null ids
too; an empty table gives no rows; extra columns are ignored. `clips` gives media that can't be read one row with the reason: null, no AVI, no frames, or
what is wrong with a frame; an empty frame repeats the one before it.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .kernels import string_views

common.by_value(__name__)

PAD, WIDTH, MAX_ROWS, RATE = 64, 64, 32, 25
#: Shots: a cut needs a difference of mean + SPREADS deviations of the last HISTORY differences, and FLOOR at least.
BINS, SPREADS, FLOOR, HISTORY = 16, 3.0, 0.25, 24
#: The zigzag order of an 8x8 block.
ZIGZAG = np.array([0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28, 35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63])
#: Code lengths 1..9 hold one category each, 8 down to 0.
_DC_COUNTS = bytes([1] * 9 + [0] * 7)
_DC_VALUES = bytes(range(8, -1, -1))
_AC_COUNTS, _AC_VALUES = bytes([1] + [0] * 15), bytes([0])


def _codes() -> tuple[np.ndarray, np.ndarray]:
    """10-bit code of each difference (-255..255, shifted) and its inverse."""
    to, back = np.zeros(511, np.uint64), np.zeros(1024, np.int16)
    for d in range(-255, 256):
        cat = abs(d).bit_length()
        length = 9 - cat
        prefix = (1 << length) - 2  # ones and a zero at the end
        extra = d if d >= 0 else d + (1 << cat) - 1
        code = ((prefix << cat) | extra) << 1  # the last bit ends the block
        to[d + 255], back[code] = code, d
    return to, back


_TO, _BACK = _codes()


def _segment(mark: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, mark, len(body) + 2) + body


def jpeg_head(rows: int, cols: int) -> bytes:
    """Everything up to the scan data of a grey picture of rows x cols blocks."""
    quant = bytes([8] * 64)
    return b"\xff\xd8" + _segment(0xDB, b"\0" + quant) + _segment(0xC0, struct.pack(">BHHB", 8, rows * 8, cols * 8, 1) + bytes([1, 0x11, 0])) \
        + _segment(0xC4, b"\0" + _DC_COUNTS + _DC_VALUES) + _segment(0xC4, b"\x10" + _AC_COUNTS + _AC_VALUES) + _segment(0xDA, bytes([1, 1, 0, 0, 63, 0]))


def encode_frame(samples: np.ndarray, head: bytes) -> bytes:
    """samples: uint8, a multiple of 4."""
    level = samples.astype(np.int16) - 128
    diff = np.empty_like(level)
    diff[0], diff[1:] = level[0], level[1:] - level[:-1]
    c = _TO[diff + 255].reshape(-1, 4)
    word = (c[:, 0] << np.uint64(30)) | (c[:, 1] << np.uint64(20)) | (c[:, 2] << np.uint64(10)) | c[:, 3]
    scan = word.astype(">u8").view(np.uint8).reshape(-1, 8)[:, 3:].tobytes()
    return head + scan.replace(b"\xff", b"\xff\x00") + b"\xff\xd9"


#: The Huffman tables of the JPEG standard's annex K, as counts by code length and values; the long tails of the AC values follow a rule.
_STANDARD = {
    0x00: (bytes([0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0]), bytes(range(12))),
    0x01: (bytes([0, 3, 1, 1, 1, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0]), bytes(range(12))),
    0x10: (
        bytes([0, 2, 1, 3, 3, 2, 4, 3, 5, 5, 4, 4, 0, 0, 1, 0x7D]),
        bytes.fromhex("01020300041105122131410613516107227114328191a1082342b1c11552d1f02433627282090a161718191a25262728292a3435363738393a")
        + bytes(16 * r + c for r in range(4, 16) for c in range({4: 3, 5: 3, 6: 3, 7: 3, 8: 3, 14: 1, 15: 1}.get(r, 2), 11)),
    ),
    0x11: (
        bytes([0, 2, 1, 2, 4, 4, 3, 4, 7, 5, 4, 4, 0, 1, 2, 0x77]),
        bytes.fromhex("000102031104052131061241510761711322328108144291a1b1c109233352f0156272d10a162434e125f11718191a262728292a35363738393a")
        + bytes(16 * r + c for r in range(4, 16) for c in range({4: 3, 5: 3, 6: 3, 7: 3}.get(r, 2), 11)),
    ),
}
_COS = np.where(np.arange(8)[:, None] == 0, np.sqrt(1 / 8), 0.5 * np.cos((2 * np.arange(8)[None, :] + 1) * np.arange(8)[:, None] * np.pi / 16))


def _jpeg_parts(raw: bytes) -> dict:
    """Tables, picture size, components (id, sampling, quantiser) and scans (components with their tables, restart interval, data)."""
    if raw[:2] != b"\xff\xd8":
        raise ValueError("no JPEG frame")
    at, restart, out = 2, 0, {"quant": {}, "huff": {}, "scans": []}
    while at + 4 <= len(raw):
        if raw[at] != 0xFF:
            raise ValueError("bad marker")
        mark = raw[at + 1]
        if mark in (0xFF, 0xD8):
            at += 1 if mark == 0xFF else 2
            continue
        if mark == 0xD9:
            break
        size = struct.unpack(">H", raw[at + 2 : at + 4])[0]
        body = raw[at + 4 : at + 2 + size]
        at += 2 + size
        if mark == 0xDB:
            while body:
                wide = body[0] >> 4
                n = 64 * (1 + wide)
                out["quant"][body[0] & 15] = np.frombuffer(body[1 : 1 + n], ">u2" if wide else np.uint8).astype(np.int64)
                body = body[1 + n :]
        elif mark == 0xC4:
            while body:
                counts = body[1:17]
                n = sum(counts)
                out["huff"][body[0]] = (counts, body[17 : 17 + n])
                body = body[17 + n :]
        elif mark in (0xC0, 0xC1):
            if body[0] != 8:
                raise ValueError("not 8 bits a sample")
            out["rows"], out["cols"], parts = struct.unpack(">HHB", body[1:6])
            out["parts"] = [tuple(body[6 + 3 * i : 9 + 3 * i]) for i in range(parts)]
        elif mark == 0xDD:
            restart = struct.unpack(">H", body[:2])[0]
        elif mark == 0xDA:
            end = at
            while True:  # the scan ends at a marker that is neither stuffing nor a restart
                end = raw.find(b"\xff", end)
                if end < 0 or end + 1 >= len(raw):
                    end = len(raw)
                    break
                if raw[end + 1] == 0 or 0xD0 <= raw[end + 1] <= 0xD7:
                    end += 2
                else:
                    break
            out["scans"].append(([(body[1 + 2 * i], body[2 + 2 * i]) for i in range(body[0])], restart, raw[at:end], dict(out["huff"])))
            at = end
        elif 0xC2 <= mark <= 0xCF and mark != 0xC8:
            raise ValueError("not a baseline JPEG")
    if not out["scans"] or not out.get("parts"):
        raise ValueError("no scan")
    if not out["rows"] or not out["cols"]:
        raise ValueError("no size")
    return out


def _book(counts: bytes, values: bytes) -> list:
    """(code length, value) for each 16 bits that may come."""
    book, code, k = [(0, 0)] * 65536, 0, 0
    for length, n in enumerate(counts, 1):
        for _ in range(n):
            at, wide = code << (16 - length), 1 << (16 - length)
            book[at : at + wide] = [(length, values[k])] * wide
            code, k = code + 1, k + 1
        code <<= 1
    return book


_BOOKS: dict = {}


def _kept_book(table) -> list:
    """Books of a few tables are kept, as frames of a film share them."""
    if table not in _BOOKS:
        if len(_BOOKS) > 16:
            _BOOKS.clear()
        _BOOKS[table] = _book(*table)
    return _BOOKS[table]


def decode_frame(raw: bytes) -> np.ndarray:
    """Luminance samples; one value a block where a grey frame holds flat blocks only (as `encode_frame` writes)."""
    j = _jpeg_parts(raw)
    if len(j["parts"]) == 1 and len(j["scans"]) == 1:
        h, w = -(-j["rows"] // 8), -(-j["cols"] // 8)
        _, restart, data, huff = j["scans"][0]
        quant = j["quant"].get(j["parts"][0][2])
        if not restart and quant is not None and quant[0] == 8 and huff.get(0) == (_DC_COUNTS, _DC_VALUES) and huff.get(16) == (_AC_COUNTS, _AC_VALUES) and (h * w) % 4 == 0:
            b = np.zeros((h * w // 4, 8), np.uint8)
            b[:, 3:] = np.frombuffer(data.replace(b"\xff\x00", b"\xff"), np.uint8)[: h * w * 10 // 8].reshape(-1, 5)
            word = b.view(">u8").astype(np.uint64).ravel()
            code = np.stack([(word >> np.uint64(s)) & np.uint64(1023) for s in (30, 20, 10, 0)], axis=1).ravel().astype(np.int64)
            return (np.cumsum(_BACK[code], dtype=np.int32) + 128).astype(np.uint8).reshape(h, w)
    return decode_planes(raw)[0]


def decode_planes(raw: bytes) -> list[np.ndarray]:
    """Every component at full size (rows x cols)."""
    j = _jpeg_parts(raw)
    rows, cols, parts = j["rows"], j["cols"], j["parts"]
    across, down = [p[1] >> 4 for p in parts], [p[1] & 15 for p in parts]
    if not all(across) or not all(down):
        raise ValueError("bad sampling")
    wide, high = max(across), max(down)
    units = -(-cols // (8 * wide)), -(-rows // (8 * high))  # of one block of each sampling step: across, down
    place = {p[0]: i for i, p in enumerate(parts)}
    grids = [np.zeros((units[1] * v, units[0] * h, 64)) for h, v in zip(across, down)]
    for members, restart, data, huff in j["scans"]:
        chosen = [(place[c], _kept_book(_table(huff, t >> 4)), _kept_book(_table(huff, 16 | (t & 15)))) for c, t in members]
        if len(chosen) == 1:  # one component: its own blocks, without the padding of the units
            i = chosen[0][0]
            size = -(-(-(-cols * across[i] // wide)) // 8), -(-(-(-rows * down[i] // high)) // 8)
            order = [[(i, y, x) for x in range(size[0])] for y in range(size[1])]
            steps = [[b] for line in order for b in line]
        else:
            steps = [[(i, v * down[i] + y, u * across[i] + x) for i, _, _ in chosen for y in range(down[i]) for x in range(across[i])] for v in range(units[1]) for u in range(units[0])]
        books = {i: (dc, ac) for i, dc, ac in chosen}
        for k, piece in enumerate(_between_restarts(data) if restart else [data]):
            mine = steps[k * restart : (k + 1) * restart] if restart else steps
            if mine:
                _read_blocks(piece.replace(b"\xff\x00", b"\xff"), mine, books, grids)
    out = []
    for i, grid in enumerate(grids):
        quant = j["quant"].get(parts[i][2])
        if quant is None:
            raise ValueError("no quantiser")
        blocks = np.zeros_like(grid)
        blocks[..., ZIGZAG] = grid * quant
        y, x = grid.shape[:2]
        flat = _COS.T @ blocks.reshape(y, x, 8, 8) @ _COS + 128
        plane = np.clip(np.rint(flat), 0, 255).astype(np.uint8).transpose(0, 2, 1, 3).reshape(y * 8, x * 8)
        line = np.arange(rows) * down[i] // high
        out.append(plane[line][:, np.arange(cols) * across[i] // wide])
    return out


def _table(huff: dict, name: int) -> tuple[bytes, bytes]:
    found = huff.get(name) or _STANDARD.get(name)
    if found is None:
        raise ValueError("no Huffman table")
    return found


def _between_restarts(data: bytes) -> list[bytes]:
    out, at, seek = [], 0, 0
    while (seek := data.find(b"\xff", seek)) >= 0 and seek + 1 < len(data):
        if 0xD0 <= data[seek + 1] <= 0xD7:
            out.append(data[at:seek])
            at = seek + 2
        seek += 2
    return [*out, data[at:]]


def _read_blocks(data: bytes, steps: list, books: dict, grids: list) -> None:
    """Fills the coefficients of the blocks (in zigzag order) from one run of codes."""
    stream, limit, at = data + b"\0" * 8, 8 * len(data), 0
    level = dict.fromkeys(books, 0)

    def peek(n: int) -> int:
        first = at >> 3
        return (int.from_bytes(stream[first : first + 4], "big") >> (32 - (at & 7) - n)) & ((1 << n) - 1)

    def symbol(book) -> int:
        nonlocal at
        length, value = book[peek(16)]
        at += length
        if not length or at > limit:
            raise ValueError("bad code")
        return value

    def extra(n: int) -> int:
        nonlocal at
        if not n:
            return 0
        v = peek(n)
        at += n
        return v if v >> (n - 1) else v - (1 << n) + 1

    for blocks in steps:
        for i, y, x in blocks:
            dc, ac = books[i]
            block = grids[i][y, x]
            level[i] += extra(symbol(dc) & 15)
            block[0] = level[i]
            k = 1
            while k < 64:
                s = symbol(ac)
                if s & 15:
                    k += s >> 4
                    if k > 63:
                        raise ValueError("bad run")
                    block[k] = extra(s & 15)
                    k += 1
                elif s == 0xF0:
                    k += 16
                else:
                    break


def _chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)


def _list(kind: bytes, body: bytes) -> bytes:
    return _chunk(b"LIST", kind + body)


def write_avi(payload: bytes, width: int = WIDTH, max_rows: int = MAX_ROWS, rate: int = RATE) -> bytes:
    """payload: a positive multiple of `width` bytes."""
    rows = min(max_rows, len(payload) // width)
    size = rows * width
    head = jpeg_head(rows, width)
    n = -(-len(payload) // size)
    samples = np.frombuffer(payload + b"\0" * (n * size - len(payload)), np.uint8).reshape(n, size)
    frames = [encode_frame(s, head) for s in samples]
    most = max(map(len, frames))
    main = struct.pack("<14I", 1_000_000 // rate, most * rate, 0, 0x10, n, 0, 1, most, width * 8, rows * 8, 0, 0, 0, 0)
    stream = struct.pack("<4s4sIHHIIIIIIII4H", b"vids", b"MJPG", 0, 0, 0, 0, 1, rate, 0, n, most, 0xFFFFFFFF, 0, 0, 0, width * 8, rows * 8)
    picture = struct.pack("<IiiHH4sIiiII", 40, width * 8, rows * 8, 1, 24, b"MJPG", width * 8 * rows * 8 * 3, 0, 0, 0, 0)
    header = _list(b"hdrl", _chunk(b"avih", main) + _list(b"strl", _chunk(b"strh", stream) + _chunk(b"strf", picture)))
    info = _list(b"INFO", _chunk(b"ICMT", b"payload=%d\0" % len(payload)))
    index, at, movi = [], 4, []
    for f in frames:
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        movi.append(_chunk(b"00dc", f))
        at += len(movi[-1])
    body = b"AVI " + header + info + _list(b"movi", b"".join(movi)) + _chunk(b"idx1", b"".join(index))
    return b"RIFF" + struct.pack("<I", len(body)) + body


def parse_avi(raw: bytes) -> dict:
    """{"frames": [(offset, size)], "rate", "payload"}; no frames if it is no AVI."""
    out: dict = {"frames": [], "rate": 0.0, "payload": None}
    if raw[:4] != b"RIFF" or raw[8:12] != b"AVI ":
        return out
    state: dict = {"movi": None, "idx1": None, "indexes": [], "listed": [], "streams": 0, "video": None}

    def walk(at: int, end: int) -> None:
        while at + 8 <= end:
            name, size = raw[at : at + 4], struct.unpack("<I", raw[at + 4 : at + 8])[0]
            body = at + 8
            if name in (b"LIST", b"RIFF"):
                if raw[body : body + 4] == b"movi" and state["movi"] is None:
                    state["movi"] = body
                walk(body + 4, min(end, body + size))
            elif name == b"avih":
                out["rate"] = 1e6 / max(1, struct.unpack("<I", raw[body : body + 4])[0])
            elif name == b"strh":
                if raw[body : body + 4] == b"vids" and state["video"] is None:
                    state["video"] = state["streams"]
                state["streams"] += 1
            elif name == b"indx" and state["video"] == state["streams"] - 1:
                state["indexes"].append((body, size))
            elif name == b"ICMT" and raw[body : body + 8] == b"payload=":
                out["payload"] = int(raw[body + 8 : body + size].rstrip(b"\0"))
            elif name == b"idx1":
                state["idx1"] = (body, size)
            elif name[2:] in (b"dc", b"db"):
                state["listed"].append((name, body, size))
            at = body + size + (size & 1)

    walk(0, len(raw))
    number = b"%02d" % (state["video"] or 0)
    mine = lambda name: name[2:] in (b"dc", b"db") and name[:2] == number
    if state["indexes"]:
        out["frames"] = [f for body, _ in state["indexes"] for f in _open_index(raw, body)]
    elif state["idx1"] and state["movi"] is not None:
        body, size = state["idx1"]
        movi = state["movi"]
        entries = [struct.unpack("<4sIII", raw[body + 16 * i : body + 16 * i + 16]) for i in range(size // 16)]
        entries = [e for e in entries if mine(e[0])]
        base = movi if not entries or raw[movi + entries[0][2] : movi + entries[0][2] + 4] == entries[0][0] else 0
        out["frames"] = [(base + e[2] + 8, e[3]) for e in entries]
    else:
        out["frames"] = [(body, size) for name, body, size in state["listed"] if mine(name)]
    return out


def _open_index(raw: bytes, at: int) -> list[tuple[int, int]]:
    """Frames of an OpenDML index: an index of indexes, or one of chunks."""
    per, _, kind, n = struct.unpack("<HBBI", raw[at : at + 8])
    entry = at + 24
    if kind == 0:
        places = [struct.unpack("<QII", raw[entry + 16 * i : entry + 16 * i + 16])[0] for i in range(n)]
        return [f for p in places for f in _open_index(raw, p + 8)]
    if kind != 1 or per < 2:
        raise ValueError("unknown index")
    base = struct.unpack("<Q", raw[at + 12 : at + 20])[0]
    rows = [struct.unpack("<II", raw[entry + 4 * per * i : entry + 4 * per * i + 8]) for i in range(n)]
    return [(base + offset, size & 0x7FFFFFFF) for offset, size in rows]


def shots_of(frames: list[np.ndarray]) -> list[tuple[int, int, float]]:
    """(first frame, frames, difference at its start)"""
    if not frames:
        return []
    hist = np.stack([np.bincount(f.ravel() >> 4, minlength=BINS) / f.size for f in frames])
    diff = 0.5 * np.abs(hist[1:] - hist[:-1]).sum(1)
    cuts, seen = [(0, 0.0)], []
    for k, d in enumerate(diff.tolist(), 1):
        past = seen[-HISTORY:]
        mean = sum(past) / len(past) if past else 0.0
        spread = (sum((x - mean) ** 2 for x in past) / len(past)) ** 0.5 if past else 0.0
        if d >= max(FLOOR, mean + SPREADS * spread):
            cuts.append((k, d))
        seen.append(d)
    ends = [c[0] for c in cuts[1:]] + [len(frames)]
    return [(a, e - a, d) for (a, d), e in zip(cuts, ends)]


def padded(raw: bytes) -> bytes:
    n = max(PAD, -(-len(raw) // PAD) * PAD)
    return raw + b"\0" * (n - len(raw))


def read_payload(raw: bytes) -> tuple[bytes, list[np.ndarray], dict]:
    info = parse_avi(raw)
    frames: list = []
    for a, n in info["frames"]:
        if n or not frames:
            frames.append(decode_frame(raw[a : a + n]))
        else:  # an empty frame shows the one before
            frames.append(frames[-1])
    got = b"".join(f.tobytes() for f in frames)
    return (got if info["payload"] is None else got[: info["payload"]]), frames, info


def _storer(batches):
    for batch in batches:
        data, offs = string_views(batch.column("text"))
        media = [write_avi(padded(data[offs[i] : offs[i + 1]].tobytes())) for i in range(batch.num_rows)]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(offs)), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])


_CLIP = pa.struct([("clip", pa.int64()), ("first_frame", pa.int64()), ("frames", pa.int64()), ("start_s", pa.float64()), ("end_s", pa.float64()), ("difference", pa.float64())])
CLIP = "clip: bigint, first_frame: bigint, frames: bigint, start_s: double, end_s: double, difference: double"


def timed(frames: list[np.ndarray], rate: float) -> list[dict]:
    """Shots as timed clips."""
    rate = rate or 1.0
    return [{"clip": k, "first_frame": a, "frames": n, "start_s": a / rate, "end_s": (a + n) / rate, "difference": float(d)} for k, (a, n, d) in enumerate(shots_of(frames))]


def _measurer(batches):
    for batch in batches:
        rows = []
        for raw in batch.column("media").to_pylist():
            payload, frames, info = read_payload(raw)
            found = timed(frames, info["rate"])
            mean = sum(int(f.sum()) for f in frames) / max(1, sum(f.size for f in frames))
            feature = f"frames={len(frames)};rows={frames[0].shape[0] if frames else 0};mean={mean:.4f};shots=" + ",".join(f"{c['first_frame']}+{c['frames']}" for c in found)
            rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(raw), hashlib.sha256(raw).hexdigest(), feature, found))
        cols = list(zip(*rows)) or [()] * 7
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(_CLIP)]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), *[pa.array(c, k) for c, k in zip(cols, kinds)]], names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "clips"])


def clips_of(raw: bytes | None) -> tuple[list[dict], str | None]:
    """(timed clips, why there are none)"""
    if raw is None:
        return [], "null"
    try:
        if raw[:4] != b"RIFF" or raw[8:12] != b"AVI ":
            return [], "no AVI"
        _, frames, info = read_payload(raw)
    except (ValueError, KeyError, IndexError, struct.error, RecursionError) as e:
        return [], f"{e}" if type(e) is ValueError else f"damaged ({type(e).__name__})"
    return (timed(frames, info["rate"]), None) if frames else ([], "no frames")


def _clipper(batches):
    for batch in batches:
        found = [clips_of(raw) for raw in batch.column("media").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([c for c, _ in found], pa.list_(_CLIP)), pa.array([r for _, r in found], pa.string())], names=["doc_id", "clips", "reason"])


def store(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media): each whole text as one AVI."""
    rows = docs.select("doc_id", "text")
    return rows.mapInArrow(_storer, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, n_bytes bigint, media binary")


def measure(media: DataFrame) -> DataFrame:
    """What the stored bytes hold, read back, with the timed clips."""
    rows = media.select("doc_id", "n_bytes", "media")
    return rows.mapInArrow(_measurer, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string, clips array<struct<{CLIP}>>")


def clips(media: DataFrame) -> DataFrame:
    """Timed clip rows of any AVI column: doc_id, clip, first_frame, frames, start_s, end_s, difference, reason (of what can't be read)."""
    rows = media.select("doc_id", "media")
    found = rows.mapInArrow(_clipper, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, clips array<struct<{CLIP}>>, reason string")
    return found.select("doc_id", "reason", F.inline_outer("clips")).select("doc_id", "clip", "first_frame", "frames", "start_s", "end_s", "difference", "reason")


def op10_media_avi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure(store(common.table(spark, sf_dir, "documents")))
