"""Media columns: payloads in baseline JPEG, and thumbnails read from its DC terms.

A payload is an image of flat 8x8 blocks, one block per byte: the DC term of a block is the byte
less 128, its quantiser step is 8 and its AC terms are none, so every decoder shows the byte as the
grey of the block, and the DC-only luminance thumbnail, one sample per block, is the payload. A
restart marker ends each 64 blocks. The reader parses the markers and tables that a file has, then
decodes the scan's Huffman codes for all restart intervals of a batch in step, in numpy. It reads other
baseline files as well, colour ones with any subsampling included, and keeps their luminance.

A frame is 64 blocks wide and at most 8191 high; longer payloads take frames one after another.

Defined cases: null is the empty text, padded to 64 zero bytes; equal texts have equal files; ids may
be null and rows may repeat; an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WIDTH = 64
MOST_ROWS = 8191
#: Code lengths of the DC categories 0 to 8; with amplitude and end of block at most 16 bits.
DC_CODES = {3: 2, 4: 2, 5: 3, 6: 4, 7: 4, 2: 5, 0: 6, 1: 7, 8: 7}


def canonical(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """symbol: (code, length) of the canonical Huffman code in order of length."""
    code, last, out = 0, 0, {}
    for symbol, n in sorted(lengths.items(), key=lambda x: x[1]):
        code <<= n - last
        out[symbol] = (code, n)
        code, last = code + 1, n
    return out


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _huffman_segment(kind: int, lengths: dict[int, int]) -> bytes:
    counts = [sum(n == k for n in lengths.values()) for k in range(1, 17)]
    return _segment(0xC4, bytes([kind, *counts, *sorted(lengths, key=lambda s: lengths[s])]))


def header(rows: int) -> bytes:
    """Everything before the scan of a frame of ``rows`` block rows."""
    return b"".join(
        (
            b"\xff\xd8",
            _segment(0xE0, b"JFIF\0\1\1\0\0\1\0\1\0\0"),
            _segment(0xDB, bytes([0, 8, *[1] * 63])),
            _segment(0xC0, struct.pack(">BHHB", 8, 8 * rows, 8 * WIDTH, 1) + b"\1\x11\0"),
            _huffman_segment(0x00, DC_CODES),
            _huffman_segment(0x10, {0: 1}),
            _segment(0xDD, struct.pack(">H", WIDTH)),
            _segment(0xDA, b"\1\1\0\0\x3f\0"),
        )
    )


def _code_table() -> tuple[np.ndarray, np.ndarray]:
    """By DC difference + 255: the bits of its code, amplitude and end of block, and how many."""
    codes, bits, sizes = canonical(DC_CODES), [], []
    for d in range(-255, 256):
        category = abs(d).bit_length()
        code, n = codes[category]
        amplitude = d if d >= 0 else d + (1 << category) - 1
        bits.append(((code << category) | amplitude) << 1)
        sizes.append(n + category + 1)
    return np.array(bits, np.uint64), np.array(sizes, np.int64)


_BITS, _SIZES = _code_table()


def scan_rows(samples: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entropy-coded bytes of rows of 64 samples, one after another, and each row's length.

    Bits are joined in pairs, pairs of pairs, and then laid into 64-bit words; ones fill up a row's
    last byte. Byte stuffing comes later.
    """
    values = samples.astype(np.int16) - 128
    diff = values.copy()
    diff[:, 1:] -= values[:, :-1]
    at = diff.astype(np.int64) + 255
    bits, sizes = _BITS[at], _SIZES[at]
    for _ in range(2):
        low = sizes[:, 1::2]
        bits = (bits[:, ::2] << low.astype(np.uint64)) | bits[:, 1::2]
        sizes = sizes[:, ::2] + low
    total = sizes.sum(axis=1)
    lengths = (total + 7) // 8
    fill = lengths * 8 - total
    bits = np.concatenate([bits, ((np.uint64(1) << fill.astype(np.uint64)) - np.uint64(1))[:, None]], axis=1)
    sizes = np.concatenate([sizes, fill[:, None]], axis=1).ravel()
    bits = bits.ravel()
    start = np.cumsum(sizes) - sizes
    word, shift = start >> 6, start & 63
    room = 64 - shift - sizes  # below 0: the rest goes to the next word
    up = np.where(room >= 0, bits << np.maximum(room, 0).astype(np.uint64), bits >> np.maximum(-room, 0).astype(np.uint64))
    up[sizes == 0] = 0
    out = np.zeros(int(word[-1]) + 2, np.uint64)
    first = np.flatnonzero(np.diff(word, prepend=-1))
    out[word[first]] = np.bitwise_or.reduceat(up, first)
    over = np.flatnonzero(room < 0)
    out[word[over] + 1] |= bits[over] << (64 + room[over]).astype(np.uint64)
    return out.astype(">u8").view(np.uint8)[: int(lengths.sum())], lengths


def encode(payloads: list[bytes]) -> list[bytes]:
    """JPEG files, one frame after another where a payload needs several."""
    if not payloads:
        return []
    data, lengths = scan_rows(np.frombuffer(b"".join(payloads), np.uint8).reshape(-1, WIDTH))
    ends = np.cumsum(lengths)
    # a zero byte after each 0xFF, and a marker after each row
    ff = np.flatnonzero(data == 0xFF) + 1
    rows = [len(p) // WIDTH for p in payloads]
    within = np.concatenate([np.arange(n) % MOST_ROWS for n in rows])
    marks = np.stack([np.full(len(within), 0xFF), 0xD0 + within % 8], axis=1).astype(np.uint8)
    data = np.insert(data, np.concatenate([ff, ends, ends]), np.concatenate([np.zeros(len(ff), np.uint8), marks[:, 0], marks[:, 1]]))
    row_ends = ends + np.searchsorted(ff, ends, side="right") + 2 * np.arange(1, len(ends) + 1)
    raw, files, row, begin = data.tobytes(), [], 0, 0
    for n in rows:
        parts = []
        for top in range(0, n, MOST_ROWS):
            row += min(MOST_ROWS, n - top)
            end = int(row_ends[row - 1])
            parts += [header(min(MOST_ROWS, n - top)), raw[begin : end - 2], b"\xff\xd9"]
            begin = end
        files.append(b"".join(parts))
    return files


class Frame:
    """The parts of one frame, and where the scan that holds its luminance (the first component) lies in the file.

    Baseline files of one to four components, with any sampling factors, in interleaved or separate scans.
    """

    def __init__(self, data: bytes, at: int):
        raw = np.frombuffer(data, np.uint8)
        tables: dict[int, bytes] = {}
        quantiser: dict[int, int] = {}
        interval, self.pattern = 0, None
        if data[at : at + 2] != b"\xff\xd8":
            raise ValueError("no start of image")
        at += 2
        while True:
            if data[at : at + 1] != b"\xff":
                raise ValueError("no marker")
            marker = data[at + 1]
            if marker == 0xD9:
                break
            size = struct.unpack_from(">H", data, at + 2)[0]
            body = data[at + 4 : at + 2 + size]
            at += 2 + size
            if marker == 0xC0:
                depth, self.height, self.width, n = struct.unpack_from(">BHHB", body)
                if depth != 8 or not self.height or not self.width:
                    raise ValueError("not an 8-bit frame of known size")
                parts = [body[6 + 3 * i : 9 + 3 * i] for i in range(n)]
                factors = {c: (f >> 4, f & 15) for c, f, _ in parts}
                light, table = parts[0][0], parts[0][2]
                self.most = tuple(max(f[k] for f in factors.values()) for k in (0, 1))
            elif 0xC1 <= marker <= 0xCF and marker not in (0xC4, 0xC8, 0xCC):
                raise ValueError("not a baseline frame")
            elif marker == 0xDB:
                while body:
                    if body[0] >> 4:
                        raise ValueError("16-bit quantisers aren't baseline")
                    quantiser[body[0] & 15] = body[1]
                    body = body[65:]
            elif marker == 0xC4:
                while body:
                    n = 17 + sum(body[1:17])
                    tables[body[0]] = body[1:n]
                    body = body[n:]
            elif marker == 0xDD:
                interval = struct.unpack(">H", body)[0]
            elif marker == 0xDA:
                scan = [(body[1 + 2 * i], body[2 + 2 * i]) for i in range(body[0])]
                self._entropy(raw, at)
                if self.pattern is None and light in [c for c, _ in scan]:
                    # one block of a component alone, or factor times factor of each in turn
                    each = {c: factors[c][0] * factors[c][1] if len(scan) > 1 else 1 for c, _ in scan}
                    self.pattern = tuple((c == light, i, tables[t >> 4], tables[0x10 | (t & 15)]) for i, (c, t) in enumerate(scan) for _ in range(each[c]))
                    self.factors = factors[light] if len(scan) > 1 else (1, 1)
                    self.share = factors[light]
                    self.step, self.quantiser = interval, quantiser[table]
                    self.begin, self.stop, self.marks, self.stuffed = at, at + self._end, self._marks, self._stuffed
                at += self._end
        if self.pattern is None:
            raise ValueError("no scan of luminance")
        self.after = at + 2

    def _entropy(self, raw: np.ndarray, at: int) -> None:
        """Where a scan's data end, its restart markers and its stuffed zeros, from ``at``."""
        ff = at + np.flatnonzero(raw[at:-1] == 0xFF)
        after = raw[ff + 1]
        ends = ff[(after != 0) & ((after < 0xD0) | (after > 0xD7))]
        if not len(ends):
            raise ValueError("the scan has no end")
        inside = ff < ends[0]
        ff, after = ff[inside] - at, after[inside]
        self._end, self._marks, self._stuffed = int(ends[0]) - at, ff[after != 0], ff[after == 0] + 1

    @property
    def blocks(self) -> tuple[int, int]:
        """Rows and columns of luminance blocks that cover the picture."""
        return tuple(-(-(-(-n * own // most)) // 8) for n, own, most in zip((self.height, self.width), self.share[::-1], self.most[::-1]))

    @property
    def units(self) -> tuple[int, int]:
        """Rows and columns of what the scan is coded in: blocks, or groups of blocks of all components."""
        if len(self.pattern) == 1:
            return self.blocks
        return tuple(-(-n // (8 * most)) for n, most in zip((self.height, self.width), self.most[::-1]))

    def key(self) -> tuple:
        return self.pattern, self.quantiser

    def picture(self, samples: np.ndarray) -> np.ndarray:
        """The thumbnail of luminance samples that stand in the order of the scan."""
        (wide, high), (rows, columns) = self.factors, self.units
        grid = samples.reshape(rows, columns, high, wide).swapaxes(1, 2).reshape(rows * high, columns * wide)
        return grid[: self.blocks[0], : self.blocks[1]]


def lookup(table: bytes) -> tuple[np.ndarray, np.ndarray]:
    """By the next 16 bits: symbol and code length (0: no code)."""
    symbols, sizes = np.zeros(1 << 16, np.uint8), np.zeros(1 << 16, np.uint8)
    code, at = 0, 16
    for n in range(1, 17):
        for _ in range(table[n - 1]):
            lo = code << (16 - n)
            symbols[lo : lo + (1 << (16 - n))], sizes[lo : lo + (1 << (16 - n))] = table[at], n
            code, at = code + 1, at + 1
        code <<= 1
    return symbols, sizes


def decode_lanes(data: np.ndarray, starts: np.ndarray, units: np.ndarray, key: tuple) -> np.ndarray:
    """Luminance DC samples (lane, block) of entropy-coded lanes in ``data``, which has no stuffing left.

    All lanes go forward together, one block a turn; a turn reads the DC code and its amplitude, then
    AC codes until each lane has met its end of block. ``units`` is how many rounds of the pattern a lane has.
    """
    pattern, quantiser = key
    tables = {t: lookup(t) for _, _, dc, ac in pattern for t in (dc, ac)}
    padded = np.concatenate([data, np.full(12, 0xFF, np.uint8)])
    words = padded[:-7].astype(np.uint64)
    for k in range(1, 8):
        words = (words << np.uint64(8)) | padded[k : len(padded) - 7 + k]
    at = starts.astype(np.int64) * 8
    most, each = int(units.max(initial=0)), sum(light for light, *_ in pattern)
    out = np.zeros((len(starts), most * each), np.uint8)
    levels = np.zeros((1 + max(c for _, c, _, _ in pattern), len(starts)), np.int64)
    lanes = np.arange(len(starts))
    uneven = units.min(initial=most) < most
    done = 0
    for u in range(most):
        if uneven:
            lanes = np.flatnonzero(units > u)
        for light, component, dc, ac in pattern:
            (dc_symbol, dc_size), (ac_symbol, ac_size), level = tables[dc], tables[ac], levels[component]
            p = at[lanes]
            window = words[p >> 3] << (p & 7).astype(np.uint64)
            head = (window >> np.uint64(48)).astype(np.int64)
            category, size = dc_symbol[head].astype(np.int64), dc_size[head].astype(np.int64)
            if not size.all():
                raise ValueError("no such DC code")
            body = (window << size.astype(np.uint64)) >> np.uint64(48)
            amplitude = (body >> (16 - category).astype(np.uint64)).astype(np.int64)
            amplitude -= np.where((amplitude << 1) >> category == 0, (np.int64(1) << category) - 1, 0)
            level[lanes] += amplitude * (category > 0)
            p = p + size + category
            seen, open_ = np.ones(len(p), np.int64), np.arange(len(p))
            while len(open_):
                q = p[open_]
                window = (words[q >> 3] << (q & 7).astype(np.uint64)) >> np.uint64(48)
                symbol, size = ac_symbol[window], ac_size[window]
                if not size.all():
                    raise ValueError("no such AC code")
                p[open_] = q + size + (symbol & 15)
                seen[open_] += np.where(symbol == 0, 64, (symbol >> 4) + 1)
                open_ = open_[seen[open_] < 64]
            at[lanes] = p
            if light:
                out[lanes, done] = np.clip((level[lanes] * quantiser + 4) // 8 + 128, 0, 255)
                done += 1
    return out


def thumbnails(files: list[bytes]) -> list[list[tuple[Frame, np.ndarray]]]:
    """Frames of every file with their DC-only luminance thumbnails, one sample per block."""
    found: list[list] = [[] for _ in files]
    groups: dict[tuple, list] = {}
    for i, data in enumerate(files):
        at = 0
        while at < len(data):
            frame = Frame(data, at)
            marks = frame.marks
            drop = np.concatenate([frame.stuffed, marks, marks + 1])
            drop.sort()
            scan = np.delete(np.frombuffer(data, np.uint8, frame.stop - frame.begin, frame.begin), drop)
            starts = np.concatenate([[0], marks + 2 - np.searchsorted(drop, marks + 1, side="right")])
            total = frame.units[0] * frame.units[1]
            step = frame.step or total
            lanes = -(-total // step)
            if lanes != len(starts):
                raise ValueError("restart markers don't fit the frame")
            counts = np.full(lanes, step)
            counts[-1] = total - step * (lanes - 1)
            groups.setdefault(frame.key(), []).append((i, len(found[i]), scan, starts, counts))
            found[i].append([frame, None])
            at = frame.after
    for key, parts in groups.items():
        base = np.cumsum([0, *(len(p[2]) for p in parts)])
        counts = np.concatenate([p[4] for p in parts])
        samples = decode_lanes(
            np.concatenate([p[2] for p in parts]), np.concatenate([p[3] + b for p, b in zip(parts, base)]), counts, key
        )
        each = sum(light for light, *_ in key[0])
        lane = 0
        for i, k, _, starts, own in parts:
            rows = samples[lane : lane + len(starts)]
            lane += len(starts)
            even = own[-1] * each == rows.shape[1] == own[0] * each
            flat = rows.ravel() if even else np.concatenate([r[: n * each] for r, n in zip(rows, own)])
            found[i][k][1] = found[i][k][0].picture(flat)
    return [[(f, t) for f, t in x] for x in found]


def thumbnail_hash(thumb: np.ndarray) -> str:
    """64 bits as hex: cells of an 8x8 grid of mean luminance against their mean."""
    rows = np.linspace(0, thumb.shape[0], 9).astype(int)
    sums = np.zeros((len(thumb) + 1, thumb.shape[1]))
    np.cumsum(thumb, axis=0, out=sums[1:])
    high = np.maximum(np.diff(rows), 1)
    top = np.minimum(rows[:-1], len(thumb) - 1)
    cells = (sums[top + high] - sums[top]).reshape(8, 8, -1).sum(axis=2) / high[:, None]
    return np.packbits(cells > cells.mean()).tobytes().hex()


def payload(text: str | None) -> tuple[int, bytes]:
    """Bytes of ``text``, and them with zeros up to a positive multiple of 64."""
    data = (text or "").encode()
    return len(data), data + bytes(-len(data) % WIDTH or (WIDTH if not data else 0))


COLUMNS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def media_columns(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep_media: bool = False, step: int = 4 << 20) -> DataFrame:
    """``doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature``.

    ``keep_media`` adds the file as ``media``. ``feature`` has width and height of the first
    frame, the hash of the thumbnails of all frames, one below the other, and the number of frames. Files are made and read some ``step`` bytes at a time.
    """
    names = [c.split()[0] for c in COLUMNS.split(", ")] + ["media"] * keep_media
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
    kinds += [pa.binary()] * keep_media

    def finish(held: list) -> pa.RecordBatch:
        rows = []
        files = encode([p for _, _, p in held])
        for (doc, n, _), data, frames in zip(held, files, thumbnails(files)):
            back = b"".join(t.tobytes() for _, t in frames)
            first, thumb = frames[0][0], np.concatenate([t for _, t in frames])
            feature = f"{first.width}x{first.height}:{thumbnail_hash(thumb)}:{len(frames)}"
            row = (
                doc, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]),
                len(data), hashlib.sha256(data).hexdigest(), feature,
            )
            rows.append((*row, data) if keep_media else row)
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held, size = [], 0
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                held.append((doc, *payload(text.as_py())))
                size += len(held[-1][2])
                if size >= step:
                    yield finish(held)
                    held, size = [], 0
            if held:
                yield finish(held)

    schema = COLUMNS + ", media binary" * keep_media
    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, schema)
