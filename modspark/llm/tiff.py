"""TIFF columns: a writer for grey pages and a reader that yields one row per page.

The reader walks the chain of image directories in either byte order, decodes strips and tiles that are stored plainly or
with PackBits, LZW or deflate, and undoes horizontal differencing. It knows samples of 1, 2, 4 (one to a byte in the result), 8, 16
and 32 bits, interleaved or in planes. The writer stores bytes as 8-bit grey samples, 64 to a row, over as many pages as
the length needs; ``varied`` picks coding, predictor, strips or tiles and byte order by the payload's checksum, so that all of
them are in use, and equal payloads are stored alike.

Defined results: null bytes give no page; a file that isn't a TIFF, is cut short, has a loop in its chain, or whose tags are missing,
zero or claim more samples than its blocks can hold, gives a row with ``error`` set and no samples for the page concerned (the claims are
checked before anything is allocated); a payload of any length is stored whole; rows with the same id stay apart (each input row's pages
follow one another); kept columns may have any names, those of the result included, which then come once, as the kept ones, with
the page's columns named with a trailing ``_``; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Tag numbers and codes of the format.
WIDTH, HEIGHT, BITS, COMPRESSION, PHOTOMETRIC, STRIP_OFFSETS, SAMPLES, ROWS_PER_STRIP, STRIP_COUNTS = 256, 257, 258, 259, 262, 273, 277, 278, 279
PLANAR, PREDICTOR, TILE_WIDTH, TILE_HEIGHT, TILE_OFFSETS, TILE_COUNTS, SAMPLE_FORMAT = 284, 317, 322, 323, 324, 325, 339
PLAIN, LZW, DEFLATE, OLD_DEFLATE, PACKBITS = 1, 5, 8, 32946, 32773
TYPE_BYTES = {1: 1, 2: 1, 3: 2, 4: 4, 5: 8, 6: 1, 7: 1, 8: 2, 9: 4, 10: 8, 11: 4, 12: 8}
TYPE_CODES = {1: "B", 3: "H", 4: "I", 6: "b", 8: "h", 9: "i"}

#: Samples in a row, and rows on a page, of files that write() makes.
ROW, PAGE_ROWS, STRIP_ROWS = 64, 1 << 15, 1 << 12
#: Bytes that a page may decode to, and that one stored byte can stand for at most (LZW's limit; deflate's is 1032).
MOST_PAGE_BYTES, MOST_GROWTH = 1 << 30, 2600


def unpack_bits(data: bytes) -> bytes:
    out, i = bytearray(), 0
    while i < len(data):
        n = data[i]
        if n < 128:
            out += data[i + 1 : i + 2 + n]
            i += n + 2
        else:
            if n > 128:
                out += data[i + 1 : i + 2] * (257 - n)
            i += 1 + (n > 128)
    return bytes(out)


def pack_bits(data: bytes) -> bytes:
    out, i, n = bytearray(), 0, len(data)
    while i < n:
        j = i + 1
        while j < n and j - i < 128 and data[j] == data[i]:
            j += 1
        if j - i > 1:
            out += bytes((257 - (j - i), data[i]))
        else:
            while j < n and j - i < 128 and not (j + 1 < n and data[j] == data[j + 1]):
                j += 1
            out.append(j - i - 1)
            out += data[i:j]
        i = j
    return bytes(out)


def unpack_lzw(data: bytes) -> bytes:
    """Codes of 9 to 12 bits, high bit first; the width grows one code early."""
    out, table, width, before = bytearray(), [], 9, None
    hold = have = 0
    start = [bytes((i,)) for i in range(256)] + [b"", b""]
    table = list(start)
    for byte in data:
        hold, have = hold << 8 | byte, have + 8
        if have < width:
            continue
        have -= width
        code, hold = hold >> have, hold & (1 << have) - 1
        if code == 256:
            table, width, before = list(start), 9, None
        elif code == 257:
            break
        else:
            if before is None:
                entry = table[code]
            else:
                entry = table[code] if code < len(table) else before + before[:1]
                if code > len(table):
                    raise ValueError("LZW code beyond the table")
                table.append(before + entry[:1])
                if len(table) + 1 >= 1 << width and width < 12:
                    width += 1
            out += entry
            before = entry
    return bytes(out)


def pack_lzw(data: bytes) -> bytes:
    out, hold, have = bytearray(), 0, 0

    def put(code, width):
        nonlocal hold, have
        hold, have = hold << width | code, have + width
        while have >= 8:
            have -= 8
            out.append(hold >> have & 255)
        hold &= (1 << have) - 1

    fresh = {bytes((i,)): i for i in range(256)}
    table, width, held = dict(fresh), 9, b""
    put(256, width)
    for k in range(len(data)):
        c = data[k : k + 1]
        if held + c in table:
            held += c
            continue
        put(table[held], width)
        table[held + c] = len(table) + 2
        if len(table) + 2 >= 4094:
            put(256, width)
            table, width = dict(fresh), 9
        elif len(table) + 2 >= 1 << width:
            width += 1
        held = c
    if held:
        put(table[held], width)
        if len(table) + 3 >= 1 << width and width < 12:
            width += 1
    put(257, width)
    if have:
        out.append(hold << 8 - have & 255)
    return bytes(out)


def _expand(data: bytes, how: int, need: int) -> bytes:
    """The block's bytes; of deflate no more than needed are made."""
    if how == PLAIN:
        return data
    if how in (DEFLATE, OLD_DEFLATE):
        return zlib.decompressobj().decompress(data, need)
    if how == PACKBITS:
        return unpack_bits(data)
    if how == LZW:
        return unpack_lzw(data)
    raise ValueError(f"compression {how}")


def _squeeze(data: bytes, how: int) -> bytes:
    return {PLAIN: lambda x: x, DEFLATE: lambda x: zlib.compress(x, 1), PACKBITS: pack_bits, LZW: pack_lzw}[how](data)


def _differ(block: np.ndarray) -> np.ndarray:
    out = block.copy()
    out[:, 1:] -= block[:, :-1]
    return out


def write(payload: bytes, compression: int = DEFLATE, predictor: int = 1, tile: tuple[int, int] | None = None, order: str = "<", row: int = ROW, page_rows: int = PAGE_ROWS, strip_rows: int = STRIP_ROWS) -> bytes:
    """payload (a multiple of row) as a TIFF of 8-bit grey pages; tile: (width, height) in place of strips."""
    samples = np.frombuffer(payload, np.uint8).reshape(-1, row)
    out = bytearray((b"II" if order == "<" else b"MM") + struct.pack(order + "HI", 42, 0))
    link = 4  # where the next directory's place is to be written
    for top in range(0, len(samples), page_rows):
        page = samples[top : top + page_rows]
        high, wide = page.shape
        blocks = []
        if tile:
            tw, th = tile
            padded = np.zeros((-(-high // th) * th, -(-wide // tw) * tw), np.uint8)
            padded[:high, :wide] = page
            blocks = [padded[y : y + th, x : x + tw] for y in range(0, high, th) for x in range(0, wide, tw)]
        else:
            blocks = [page[y : y + strip_rows] for y in range(0, high, strip_rows)]
        places, counts = [], []
        for block in blocks:
            data = _squeeze((_differ(block) if predictor == 2 else np.ascontiguousarray(block)).tobytes(), compression)
            places.append(len(out))
            counts.append(len(data))
            out += data + b"\0" * (len(data) & 1)
        tags = {WIDTH: [wide], HEIGHT: [high], BITS: [8], COMPRESSION: [compression], PHOTOMETRIC: [1], SAMPLES: [1], PREDICTOR: [predictor]}
        tags |= {TILE_WIDTH: [tile[0]], TILE_HEIGHT: [tile[1]], TILE_OFFSETS: places, TILE_COUNTS: counts} if tile else {ROWS_PER_STRIP: [strip_rows], STRIP_OFFSETS: places, STRIP_COUNTS: counts}
        body = b""
        for tag, values in sorted(tags.items()):
            if len(values) == 1:
                value = struct.pack(order + "I", values[0])
            else:
                value = struct.pack(order + "I", len(out))
                out += struct.pack(f"{order}{len(values)}I", *values)
            body += struct.pack(order + "HHI", tag, 4, len(values)) + value
        struct.pack_into(order + "I", out, link, len(out))
        link = len(out) + 2 + len(body)
        out += struct.pack(order + "H", len(tags)) + body + struct.pack(order + "I", 0)
    return bytes(out)


#: Codings, predictors, blocks and byte orders that varied() picks from.
VARIETY = [(how, predictor, tile, order) for how in (DEFLATE, PACKBITS, LZW, PLAIN) for predictor in (1, 2) for tile in (None, (16, 64)) for order in "<>"]


def varied(payload: bytes) -> bytes:
    """payload as a TIFF whose coding is picked by its checksum."""
    how, predictor, tile, order = VARIETY[zlib.crc32(payload) % len(VARIETY)]
    return write(payload, how, predictor, tile, order)


def _tags(data: bytes, at: int, order: str) -> tuple[dict[int, tuple], int]:
    (n,) = struct.unpack_from(order + "H", data, at)
    found = {}
    for k in range(n):
        tag, kind, count = struct.unpack_from(order + "HHI", data, at + 2 + 12 * k)
        size = TYPE_BYTES.get(kind, 0) * count
        if kind not in TYPE_CODES or not size:
            continue
        where = at + 10 + 12 * k if size <= 4 else struct.unpack_from(order + "I", data, at + 10 + 12 * k)[0]
        found[tag] = struct.unpack_from(f"{order}{count}{TYPE_CODES[kind]}", data, where)
    return found, struct.unpack_from(order + "I", data, at + 2 + 12 * n)[0]


def _page(data: bytes, tags: dict[int, tuple], order: str) -> tuple[int, int, int, int, np.ndarray]:
    one = lambda tag, default: tags.get(tag, (default,))[0]
    wide, high, per = tags[WIDTH][0], tags[HEIGHT][0], one(SAMPLES, 1)
    bits, how, predictor, planar = one(BITS, 1), one(COMPRESSION, PLAIN), one(PREDICTOR, 1), one(PLANAR, 1) == 2
    if bits not in (1, 2, 4, 8, 16, 32) or predictor not in (1, 2) or (predictor == 2 and bits < 8) or len(set(tags.get(BITS, (1,)))) > 1:
        raise ValueError(f"{bits} bits, predictor {predictor}")
    tiled = TILE_OFFSETS in tags
    bw, bh = (tags[TILE_WIDTH][0], tags[TILE_HEIGHT][0]) if tiled else (wide, min(one(ROWS_PER_STRIP, high), high))
    if min(wide, high, per, bw, bh) <= 0:
        raise ValueError("a size of zero")
    places, counts = (tags[TILE_OFFSETS], tags[TILE_COUNTS]) if tiled else (tags[STRIP_OFFSETS], tags[STRIP_COUNTS])
    kind = np.dtype(f"{order}u{max(bits // 8, 1)}")
    within = 1 if planar else per  # samples of a pixel that stand together
    line = -(-bw * within * bits // 8)  # bytes of a block's row
    across, down = -(-wide // bw), -(-high // bh)
    each = across * down
    if len(places) != len(counts) or len(places) < each * (per if planar else 1):
        raise ValueError("blocks are missing")
    if any(place + count > len(data) for place, count in zip(places, counts, strict=True)):
        raise ValueError("cut short")
    claimed, stored = high * wide * per * kind.itemsize, sum(counts)
    if claimed > MOST_PAGE_BYTES or down * bh * across * line > (stored + 64) * (1 if how == PLAIN else MOST_GROWTH) + bh * line * across:
        raise ValueError(f"{claimed} bytes of samples claimed by {stored} stored ones")
    out = np.empty((high, wide, per), kind)
    for k in range(each * (per if planar else 1)):
        plane, at = divmod(k, each)
        y, x = at // across * bh, at % across * bw
        rows = bh if tiled else min(bh, high - y)
        raw = _expand(data[places[k] : places[k] + counts[k]], how, rows * line)
        if bits < 8:
            packed = np.frombuffer(raw, np.uint8, rows * line).reshape(rows, line)
            single = np.unpackbits(packed, axis=1).reshape(rows, -1, bits)
            block = (single @ (1 << np.arange(bits - 1, -1, -1, dtype=np.uint8))).astype(np.uint8)[:, : bw * within].reshape(rows, bw, within)
        else:
            block = np.frombuffer(raw, kind, rows * bw * within).reshape(rows, bw, within)
        if predictor == 2:
            block = np.cumsum(block, axis=1, dtype=kind.newbyteorder("="))
        part = block[: high - y, : wide - x]
        if planar:
            out[y : y + rows, x : x + bw, plane : plane + 1] = part
        else:
            out[y : y + rows, x : x + bw] = part
    return wide, high, per, bits, out


def read(data: bytes | None):
    """(page, width, height, samples per pixel, bits, sample bytes, error) of each page."""
    if data is None:
        return
    try:
        order = {b"II": "<", b"MM": ">"}[data[:2]]
        magic, at = struct.unpack_from(order + "HI", data, 2)
        if magic != 42:
            raise ValueError("no TIFF")
    except (KeyError, ValueError, struct.error) as e:
        yield 0, None, None, None, None, None, f"header: {e}"
        return
    seen, page = set(), 0
    while at:
        if at in seen:
            yield page, None, None, None, None, None, "the chain of directories has a loop"
            return
        seen.add(at)
        try:
            tags, at = _tags(data, at, order)
        except (struct.error, OverflowError, MemoryError) as e:
            yield page, None, None, None, None, None, f"directory: {e}"
            return
        try:
            wide, high, per, bits, samples = _page(data, tags, order)
            yield page, wide, high, per, bits, samples.tobytes(), None
        except (KeyError, ValueError, zlib.error, IndexError, ZeroDivisionError, OverflowError) as e:
            yield page, None, None, None, None, None, f"page: {e!r}"
        page += 1


PAGES = "page int, width int, height int, samples_per_pixel int, bits int, samples binary, error string"


def pages(df: DataFrame, bytes_col: str = "media", keep_cols: tuple[str, ...] = ()) -> DataFrame:
    """One row per page of each file; keep_cols are carried along. The pages of a file follow one another in one task."""
    kept_fields = {f.name: f.dataType.simpleString() for f in df.schema}
    own = common.fresh(df.select(*keep_cols), *(x.split()[0] for x in PAGES.split(", ")))
    names = [*keep_cols, *own]
    schema = ", ".join([f"`{c}` {kept_fields[c]}" for c in keep_cols] + [f"`{c}` {x.split()[1]}" for c, x in zip(own, PAGES.split(", "), strict=True)])

    def walk(batches):
        for pdf in batches:
            held, size = [], 0
            for *kept, data in pdf.itertuples(index=False, name=None):
                for row in read(data):
                    held.append((*kept, *row))
                    size += len(row[5] or b"")
                    if size > 16 << 20:
                        yield pd.DataFrame(held, columns=names)
                        held, size = [], 0
            if held:
                yield pd.DataFrame(held, columns=names)

    source, = common.fresh(df.select(*keep_cols), "bytes")
    return df.select(*keep_cols, F.col(bytes_col).alias(source)).mapInPandas(walk, schema)


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """doc_id (0 where gone is true), gone, n_bytes, media: each text's UTF-8 bytes, padded with 0 to a positive multiple of 64, as a TIFF;
    how: write()'s parameters, without any the coding is varied()."""

    def make(batches):
        for pdf in batches:
            n, media = [], []
            for text in pdf["text"]:
                raw = text.encode("utf-8", "surrogatepass")
                n.append(len(raw))
                payload = raw + b"\0" * (-len(raw) % ROW or (0 if raw else ROW))
                media.append(write(payload, **how) if how else varied(payload))
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "gone": pdf["gone"], "n_bytes": n, "media": media})

    src = docs.select(*common.id_and_gone(id_col), common.whole_text(docs, text_col).alias("text"))
    return src.mapInPandas(make, "doc_id long, gone boolean, n_bytes long, media binary")


def feature(samples: np.ndarray, n_pages: int) -> str:
    """Pages, mean, deviation, mean step between neighbours, and the two most common samples."""
    counts = np.bincount(samples, minlength=256)
    n, steps = len(samples), samples.reshape(-1, ROW).astype(np.int16)
    mean = float(counts @ np.arange(256)) / n
    spread = (float(counts @ np.arange(256) ** 2) / n - mean * mean) ** 0.5 if n else 0.0
    step = float(np.abs(np.diff(steps, axis=1)).mean())
    first, second = np.argsort(-counts, kind="stable")[:2]
    return f"p{n_pages};m{mean:.4f};s{spread:.4f};d{step:.4f};t{first},{second}"


DIGESTS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _digests(batches):
    """Joins the pages of each file again: page 0 begins a file."""
    held, parts = None, []

    def done():
        payload = b"".join(parts)
        doc_id, n_bytes, media_bytes, media_sha = held
        return (doc_id, n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), media_bytes, media_sha, feature(np.frombuffer(payload, np.uint8), len(parts)))

    for pdf in batches:
        rows = []
        for doc_id, gone, n_bytes, media_bytes, media_sha, page, samples, error in pdf[["doc_id", "gone", "n_bytes", "media_bytes", "media_sha256", "page", "samples", "error"]].itertuples(index=False, name=None):
            if error is not None:
                raise ValueError(f"stored page can't be read back: {error}")
            if page == 0:
                if held is not None:
                    rows.append(done())
                held, parts = (None if gone else int(doc_id), n_bytes, media_bytes, media_sha), []
            parts.append(samples)
        yield common.frame(rows, DIGESTS)
    if held is not None:
        yield common.frame([done()], DIGESTS)


def op4_tiff_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    stored = store(common.documents(spark, sf_dir))
    told = stored.withColumn("media_bytes", F.length("media").cast("long")).withColumn("media_sha256", F.sha2("media", 256))
    return pages(told, "media", ("doc_id", "gone", "n_bytes", "media_bytes", "media_sha256")).mapInPandas(_digests, DIGESTS)
