"""GIF: LZW code streams, palettes, disposal, transparency, and frame tables.

``parse`` reads any GIF (87a, 89a; local and global palettes, interlacing, graphic
control blocks); ``compose`` applies disposal and transparency to give what a viewer
shows; ``frames`` does both for a DataFrame of GIFs and stores a row for each timed
frame with its colour histogram. ``store`` writes bytes losslessly as 8-bit grey
samples, 192 to a row, in frames of ``ROWS`` rows, each ``DELAY`` hundredths of a second
after the last, with LZW codes that grow to twelve bits. ``digest`` reads its own files
the same way: code table, palette, composed frames and their histograms.

Defined cases: null and empty texts store one row of spaces; broken GIFs give no
frames and a message; repeated rows repeat; extra columns are ignored.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.session import prepare

ROW, ROWS, DELAY = 192, 1024, 10
#: Entries of a code table, and codes that are cut out of a stream at a time.
TABLE, _CUT = 4096, 4608


@dataclass
class Frame:
    left: int
    top: int
    width: int
    height: int
    delay_cs: int
    disposal: int
    transparent: int | None
    palette: np.ndarray  # rows of red, green, blue
    pixels: np.ndarray  # palette indices, height x width


def _blocks(data: bytes) -> bytes:
    """Length-prefixed sub-blocks of at most 255 bytes, and the empty one that ends them."""
    whole = len(data) // 255
    a = np.empty((whole, 256), np.uint8)
    a[:, 0] = 255
    a[:, 1:] = np.frombuffer(data, np.uint8, whole * 255).reshape(whole, 255)
    rest = data[whole * 255 :]
    return a.tobytes() + (bytes([len(rest)]) + rest if rest else b"") + b"\0"


def _unblock(data: bytes, at: int) -> tuple[bytes, int]:
    parts = []
    while n := data[at]:
        parts.append(data[at + 1 : at + 1 + n])
        at += n + 1
    return b"".join(parts), at + 1


def _widths(least: int, begin: int, n: int) -> np.ndarray:
    """Bits of the codes ``begin`` to ``begin + n`` after a clear code: a code has room for the entries that its reader has made by then."""
    entries = (1 << least) + 1 + np.maximum(np.arange(begin, begin + n), 1)
    bits = np.frexp(np.minimum(entries, TABLE - 1).astype(np.float64))[1]
    return np.maximum(bits, least + 1).astype(np.int64)


def lzw_encode(pixels: bytes, least: int = 8) -> bytes:
    """The code stream of palette indices below 2**least; the table starts anew when it is full."""
    clear, end = 1 << least, (1 << least) + 1
    table: dict[int, int] = {}
    codes, nxt = [clear], end + 1
    put, find = codes.append, table.get
    if pixels:
        held = pixels[0]
        for p in pixels[1:]:
            key = held << 8 | p
            code = find(key)
            if code is not None:
                held = code
                continue
            put(held)
            if nxt < TABLE:
                table[key] = nxt
                nxt += 1
            else:
                put(clear)
                table.clear()
                nxt = end + 1
            held = p
        put(held)
    put(end)
    c = np.array(codes, np.int64)
    place = np.arange(len(c))
    starts = np.flatnonzero(c == clear)
    since = place - 1 - np.concatenate([[0], starts])[np.searchsorted(starts, place, "left")]  # codes since the clear code before
    widths = _widths(least, 0, TABLE + 2)[np.maximum(since, 0)]
    ends = np.cumsum(widths)
    at = ends - widths
    v = c << (at & 7)
    size = int(-(-ends[-1] // 8))
    out = sum(np.bincount((at >> 3) + k, v >> 8 * k & 255, size + 3) for k in range(3))  # codes share no bit
    return out[:size].astype(np.uint8).tobytes()


def lzw_decode(data: bytes, least: int, n: int) -> np.ndarray:
    """``n`` palette indices from a code stream whose smallest code has ``least`` bits; what is missing is 0."""
    clear, end = 1 << least, (1 << least) + 1
    fresh = [bytes([i]) for i in range(clear)] + [b"", b""]
    raw = np.concatenate([np.frombuffer(data, np.uint8), np.zeros(4, np.uint8)]).astype(np.int64)
    bits, at, since = len(data) * 8, 0, 0
    table, before, out, size, going = list(fresh), b"", [], 0, True
    while going and size < n:
        widths = _widths(least, since, _CUT)
        ends = at + np.cumsum(widths)
        k = int(np.searchsorted(ends, bits, "right"))  # whole codes that are left
        if not k:
            break
        begins = ends[:k] - widths[:k]
        b = begins >> 3
        codes = (raw[b] | raw[b + 1] << 8 | raw[b + 2] << 16) >> (begins & 7) & (1 << widths[:k]) - 1
        stops = np.flatnonzero((codes == clear) | (codes == end))
        stop = int(stops[0]) if len(stops) else k
        for code in codes[:stop].tolist():
            if code < len(table):
                entry = table[code]
            elif code == len(table) and before:
                entry = before + before[:1]
            else:
                raise ValueError("code beyond the table")
            out.append(entry)
            size += len(entry)
            if before and len(table) < TABLE:
                table.append(before + entry[:1])
            before = entry
        if stop < k:
            at, since, going = int(ends[stop]), 0, codes[stop] == clear
            table, before = list(fresh), b""
        else:
            at, since = int(ends[k - 1]), since + k
    return np.frombuffer(b"".join(out)[:n].ljust(n, b"\0"), np.uint8)


_GREY = np.repeat(np.arange(256, dtype=np.uint8), 3).tobytes()


def store(payload: bytes) -> bytes:
    """A GIF whose frames hold the payload, ``ROW`` samples to a row; its length must be a multiple of ``ROW``."""
    rows = len(payload) // ROW
    parts = [b"GIF89a", struct.pack("<HHBBB", ROW, min(rows, ROWS), 0xF7, 0, 0), _GREY]
    for top in range(0, rows, ROWS):
        h = min(ROWS, rows - top)
        parts += [b"\x21\xf9\x04", struct.pack("<BHB", 1 << 2, DELAY, 0), b"\0", b"\x2c", struct.pack("<HHHHB", 0, 0, ROW, h, 0), b"\x08", _blocks(lzw_encode(payload[top * ROW : (top + h) * ROW]))]
    return b"".join([*parts, b"\x3b"])


def parse(data: bytes) -> tuple[int, int, list[Frame]]:
    """Screen width and height, and the frames as they are stored."""
    if data[:6] not in (b"GIF87a", b"GIF89a"):
        raise ValueError("not a GIF")
    wide, high, flags = struct.unpack_from("<HHB", data, 6)
    at, shared = 13, None
    if flags & 0x80:
        n = 2 << (flags & 7)
        shared = np.frombuffer(data, np.uint8, n * 3, at).reshape(n, 3)
        at += n * 3
    control, out = (0, 0, None), []
    while at < len(data) and data[at] != 0x3B:
        if data[at] == 0x21:
            body, nxt = _unblock(data, at + 2)
            if data[at + 1] == 0xF9 and len(body) >= 4:
                f, delay, index = struct.unpack_from("<BHB", body)
                control = (delay, f >> 2 & 7, index if f & 1 else None)
            at = nxt
        elif data[at] == 0x2C:
            left, top, w, h, f = struct.unpack_from("<HHHHB", data, at + 1)
            at += 10
            palette = shared
            if f & 0x80:
                n = 2 << (f & 7)
                palette = np.frombuffer(data, np.uint8, n * 3, at).reshape(n, 3)
                at += n * 3
            if palette is None:
                raise ValueError("no palette")
            least = data[at]
            body, at = _unblock(data, at + 1)
            px = lzw_decode(body, least, w * h).reshape(h, w)
            if f & 0x40:
                rows = [y for a, s in ((0, 8), (4, 8), (2, 4), (1, 2)) for y in range(a, h, s)]
                real = np.empty_like(px)
                real[rows] = px
                px = real
            out.append(Frame(left, top, w, h, *control, palette, px))
            control = (0, 0, None)
        else:
            raise ValueError("unknown block")
    return wide, high, out


def compose(wide: int, high: int, frames: list[Frame]):
    """What is shown at each frame: red, green, blue, opacity."""
    canvas = np.zeros((high, wide, 4), np.uint8)
    for f in frames:
        kept = canvas.copy() if f.disposal == 3 else None
        h, w = max(0, min(f.height, high - f.top)), max(0, min(f.width, wide - f.left))
        px = f.pixels[:h, :w]
        known = np.minimum(px, len(f.palette) - 1)
        part = np.concatenate([f.palette[known], np.full((h, w, 1), 255, np.uint8)], 2)
        area = canvas[f.top : f.top + h, f.left : f.left + w]
        if f.transparent is None:
            area[:] = part
        else:
            seen = px != f.transparent
            area[seen] = part[seen]
        yield canvas
        if f.disposal == 2:
            area[:] = 0
        elif f.disposal == 3:
            canvas = kept


def histogram(rgba: np.ndarray, bins: int = 4) -> list[int]:
    """Counts of the opaque pixels' colours, ``bins`` to a channel."""
    seen = rgba[rgba[..., 3] > 0][:, :3].astype(np.int64) * bins >> 8
    return np.bincount((seen[:, 0] * bins + seen[:, 1]) * bins + seen[:, 2], minlength=bins**3).tolist()


FRAMES = "id long, frame int, left int, top int, width int, height int, delay_cs int, start_cs int, disposal int, transparent int, rgba binary, histogram array<int>, error string"


def frames(media: DataFrame, key: str = "media_id", column: str = "gif") -> DataFrame:
    """A row for each timed frame of each GIF as shown, with its histogram of 64 colours."""
    prepare(media.sparkSession)

    def run(batches):
        import pyarrow as pa

        names = [x.split()[0] for x in FRAMES.split(", ")]
        kinds = [pa.int64(), *[pa.int32()] * 9, pa.binary(), pa.list_(pa.int32()), pa.string()]
        for b in batches:
            for k, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                rows, clock = [], 0
                try:
                    wide, high, all_frames = parse(data or b"")
                    for i, (f, shown) in enumerate(zip(all_frames, compose(wide, high, all_frames), strict=False)):
                        rows.append((k, i, f.left, f.top, f.width, f.height, f.delay_cs, clock, f.disposal, f.transparent, shown.tobytes(), histogram(shown), None))
                        clock += f.delay_cs
                except (ValueError, IndexError, struct.error) as e:
                    rows = [(k, *[None] * 11, str(e))]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return media.select(F.col(key).cast("long"), column).mapInArrow(run, FRAMES)


def _stored(docs: DataFrame, schema: str, row) -> DataFrame:
    prepare(docs.sparkSession)
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            got = [row(t) for t in b.column(1).to_pylist()]
            kinds = [{"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}[x.split()[1]] for x in schema.split(", ")]
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([g[i] for g in got], t) for i, t in enumerate(kinds[1:])]], names)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").alias("__text")).mapInArrow(run, schema)


def payload_of(text: str | None) -> tuple[int, bytes]:
    """Bytes of a text, and the same padded with spaces to a positive multiple of ``ROW``."""
    raw = (text or "").encode()
    return len(raw), raw.ljust(max(ROW, -(-len(raw) // ROW) * ROW), b" ")


def texts_as_gifs(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, gif)."""
    return _stored(docs, "doc_id long, n_bytes long, gif binary", lambda t: ((p := payload_of(t))[0], store(p[1])))


def shown_samples(media: bytes) -> tuple[bytes, str]:
    """What ``store`` stored, read from the composed frames, and the feature: frames, duration, and each one's time and histogram (bin x pixels)."""
    wide, high, got = parse(media)
    samples, said, clock = [], [], 0
    for f, shown in zip(got, compose(wide, high, got), strict=True):
        samples.append(shown[f.top : f.top + f.height, f.left : f.left + f.width, 0].tobytes())
        said.append(f"{clock}+{f.delay_cs}=" + ",".join(f"{k}x{v}" for k, v in enumerate(histogram(shown)) if v))
        clock += f.delay_cs
    return b"".join(samples), f"{len(got)}:{clock}:" + ";".join(said)


def digest(docs: DataFrame) -> DataFrame:
    """Each text stored as a GIF and read back: sizes, hashes, and the times and colour histograms of its frames."""

    def row(text):
        import hashlib
        import zlib

        n, payload = payload_of(text)
        media = store(payload)
        back, feature = shown_samples(media)
        return n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-16:]), len(media), hashlib.sha256(media).hexdigest(), feature

    return _stored(docs, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string", row)
