"""Media columns: Netpbm and BMP to numpy arrays, area resizing by integral images, NPY tiles, difference hashes."""

from __future__ import annotations

import hashlib
import io
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import new_path, ship, store
from .token_files import open_fs
from .words import flatten, released, slices

ROW = 64


def decode_image(data: bytes) -> np.ndarray:
    """Samples as height x width (x 3) array: PBM, PGM, PPM (plain or raw) or uncompressed BMP of 8, 24 or 32 bits."""
    if data[:2] == b"BM":
        return _bmp(data)
    if len(data) > 2 and data[:1] == b"P" and data[1:2] in b"123456":
        return _netpbm(data)
    raise ValueError("neither Netpbm nor BMP")


def _netpbm(data: bytes) -> np.ndarray:
    kind, at, values = data[1] - 48, 2, []
    wanted = 2 if kind in (1, 4) else 3
    while len(values) < wanted:
        while data[at : at + 1].isspace() or data[at : at + 1] == b"#":
            at = data.index(b"\n", at) + 1 if data[at : at + 1] == b"#" else at + 1
        end = at
        while data[end : end + 1].isdigit():
            end += 1
        values.append(int(data[at:end]))
        at = end
    at += 1  # the one white-space byte after the header
    width, height = values[:2]
    top = values[2] if wanted == 3 else 1
    depth = 3 if kind in (3, 6) else 1
    if kind in (1, 2, 3):
        body = data[at - 1 :]
        if kind == 1:
            body = b" ".join(bytes([c]) for c in body if c in b"01")
        out = np.array(body.split(), np.int64)[: width * height * depth]
        out = out.astype(np.uint16 if top > 255 else np.uint8)
    elif kind == 4:
        rows = np.frombuffer(data, np.uint8, height * -(-width // 8), at).reshape(height, -1)
        out = np.unpackbits(rows, axis=1)[:, :width].reshape(-1)
    else:
        out = np.frombuffer(data, ">u2" if top > 255 else np.uint8, width * height * depth, at)
    if kind in (1, 4):
        out = (1 - out) * 255  # a set bit is black
    return out.reshape((height, width, 3) if depth == 3 else (height, width))


def _bmp(data: bytes) -> np.ndarray:
    word = lambda at, n=4, signed=False: int.from_bytes(data[at : at + n], "little", signed=signed)
    at, width, height, bits, packed = word(10), word(18, signed=True), word(22, signed=True), word(28, 2), word(30)
    if packed not in (0, 3) or bits not in (8, 24, 32):
        raise ValueError("this kind of BMP isn't supported")
    stride = -(-width * bits // 32) * 4
    rows = np.frombuffer(data, np.uint8, stride * abs(height), at).reshape(abs(height), stride)
    rows = rows if height < 0 else rows[::-1]
    if bits == 8:
        colours = np.frombuffer(data, np.uint8, (word(46) or 256) * 4, 14 + word(14)).reshape(-1, 4)[:, 2::-1]
        grid = rows[:, :width]
        return grid if (colours == colours[:, :1]).all() and (colours[:, 0] == np.arange(len(colours))).all() else colours[grid]
    step = bits // 8
    return rows[:, : width * step].reshape(abs(height), width, step)[:, :, 2::-1]


def encode_pgm(samples: np.ndarray) -> bytes:
    return b"P5\n%d %d\n255\n" % (samples.shape[1], samples.shape[0]) + samples.astype(np.uint8).tobytes()


def encode_bmp(samples: np.ndarray) -> bytes:
    """8-bit grey BMP, bottom row first."""
    height, width = samples.shape
    rows = np.zeros((height, -(-width // 4) * 4), np.uint8)
    rows[:, :width] = samples[::-1]
    table = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 4, axis=1)
    table[:, 3] = 0
    at = 54 + 1024
    ints = lambda *x: b"".join(v.to_bytes(n, "little") for v, n in x)
    return b"BM" + ints((at + rows.size, 4), (0, 4), (at, 4), (40, 4), (width, 4), (height, 4), (1, 2), (8, 2), (0, 4), (rows.size, 4), (0, 8), (256, 4), (0, 4)) + table.tobytes() + rows.tobytes()


def grey(samples: np.ndarray) -> np.ndarray:
    return samples if samples.ndim == 2 else samples.astype(np.float64) @ np.array([0.299, 0.587, 0.114])


#: Samples of an image that are summed at once.
STRIP = 1 << 18


def area_resize(samples: np.ndarray, height: int, width: int) -> np.ndarray:
    """Mean over each target cell's area, with parts of samples at its edges, from an integral image. Of that only the
    rows at cell edges are kept: strips of rows are summed on top of what lies above them, so memory doesn't grow with the image."""
    rows, columns = samples.shape[:2]
    ys, xs = np.linspace(0, rows, height + 1), np.linspace(0, columns, width + 1)
    whole = np.minimum(ys.astype(np.int64), rows - 1)
    above, edge = np.zeros(columns), np.empty((height + 1, columns))
    step = max(1, STRIP // columns)
    for lo in range(0, rows, step):
        strip = np.cumsum(grey(samples[lo : lo + step]), axis=0, dtype=np.float64)
        for k in np.flatnonzero((whole >= lo) & (whole < lo + len(strip))):
            at = whole[k] - lo
            before = strip[at - 1] if at else 0.0
            edge[k] = above + before + (strip[at] - before) * (ys[k] - whole[k])
        above = above + strip[-1]
    total = np.concatenate([np.zeros((height + 1, 1)), np.cumsum(edge, axis=1)], axis=1)
    lo = np.minimum(xs.astype(np.int64), columns - 1)
    total = total[:, lo] * (1 - (xs - lo)) + total[:, lo + 1] * (xs - lo)
    return np.diff(np.diff(total, axis=0), axis=1) / ((rows / height) * (columns / width))


def difference_hash(samples: np.ndarray, size: int = 8) -> str:
    """Hex of whether each cell is darker than its right neighbour, after resizing to size x (size + 1)."""
    small = area_resize(samples, size, size + 1)
    return np.packbits(small[:, 1:] > small[:, :-1] + 1e-9).tobytes().hex()


def tile(samples: np.ndarray, side: int = 16) -> np.ndarray:
    return np.clip(np.rint(area_resize(samples, side, side)), 0, 255).astype(np.uint8)


def payload(text: bytes) -> bytes:
    """text and zero bytes up to a positive multiple of ROW."""
    return text + bytes(-len(text) % ROW if text else ROW)


#: How texts are stored: an image of n rows takes the (n mod 2)-th.
FORMATS = (encode_pgm, encode_bmp)
#: Tiles of a file, at most.
TILES = 4096
_UNREADABLE = (ValueError, TypeError, IndexError)


def text_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media: each text's payload as an 8-bit grey image of ROW columns, in raw PGM if its rows are
    even in number and in BMP if odd. Null text is empty; repeated rows each give a row; null doc_ids stay null; an empty
    table gives an empty one; other columns, whatever their names, are ignored."""
    ship(docs.sparkSession)

    def make(batches):
        for b in batches:
            for part in slices(b, "text"):
                raw, offs = flatten(part.column("text"))
                grids = [np.frombuffer(payload(raw[i:j].tobytes()), np.uint8).reshape(-1, ROW) for i, j in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
                media = [FORMATS[len(x) % 2](x) for x in grids]
                yield pa.RecordBatch.from_pydict({"doc_id": part.column("doc_id"), "n_bytes": pa.array(np.diff(offs)), "media": pa.array(media, pa.binary())})

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(released(make), "doc_id long, n_bytes long, media binary")


_DESCRIBED = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
_INDEX = _DESCRIBED + ", path string, row long"


def described(data: bytes | None, side: int) -> tuple[tuple, np.ndarray | None]:
    """payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature of stored media, and its tile. What
    can't be decoded has a digest of the stored form alone; null media have nothing."""
    stored = (None, None) if data is None else (len(data), hashlib.sha256(data).hexdigest())
    try:
        samples = decode_image(data)
        body = np.ascontiguousarray(samples)
        return (body.nbytes, hashlib.sha256(body).hexdigest(), zlib.crc32(body.reshape(-1).view(np.uint8)[-ROW:]), *stored, difference_hash(samples)), tile(samples, side)
    except _UNREADABLE:
        return (None, None, None, *stored, None), None


def write_tiles(media: DataFrame, folder: str | None = None, side: int = 16) -> DataFrame:
    """From stored media (doc_id, n_bytes, media): digests of the decoded samples and of the stored form, the difference
    hash, and the path of an NPY file of stacked side x side tiles and the tile's row there. Stored; a row for each row.

    Files hold TILES tiles at most, written as they fill. Media that can't be decoded, and null media, keep their row with
    null path, row and feature. Repeated rows have a tile each; an empty table writes nothing; other columns are ignored.
    """
    spark = media.sparkSession
    ship(spark)
    folder = folder or new_path(spark, "tiles")
    names = [c.split()[0] for c in _INDEX.split(", ")]
    kinds = [pa.int64() if c.endswith("long") else pa.string() for c in _INDEX.split(", ")]

    def write(batches):
        rows, tiles = [], []

        def flush():
            path = None
            if tiles:
                fs, root = open_fs(folder)
                fs.create_dir(root, recursive=True)
                name = f"tiles-{uuid.uuid4().hex}.npy"
                out = io.BytesIO()
                np.save(out, np.stack(tiles))
                with fs.open_output_stream(f"{root}/{name}") as f:
                    f.write(out.getvalue())
                path = f"{folder}/{name}"
            whole = [(*told, None if row is None else path, row) for *told, row in rows]
            out = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*whole, strict=True), kinds, strict=True)], names=names)
            rows.clear()
            tiles.clear()
            return out

        for b in batches:
            for key, n, data in zip(b.column("doc_id").to_pylist(), b.column("n_bytes").to_pylist(), b.column("media"), strict=True):
                told, small = described(data.as_py(), side)
                rows.append((key, n, *told, None if small is None else len(tiles)))
                if small is not None:
                    tiles.append(small)
                if len(rows) == TILES:
                    yield flush()
        if rows:
            yield flush()

    return store(media.select("doc_id", "n_bytes", "media").mapInArrow(released(write), _INDEX), "tile-index")


def read_tiles(index: DataFrame) -> DataFrame:
    """index, as write_tiles gives it, with tile_crc32 in place of path and row: of the tile's bytes as read from its file;
    null where there is no tile. A file is read once for the rows of it that stand together."""
    ship(index.sparkSession)

    def read(batches):
        held, stack = None, None
        for b in batches:
            crc = []
            for path, row in zip(b.column("path").to_pylist(), b.column("row").to_pylist(), strict=True):
                if path is not None and path != held:
                    fs, name = open_fs(path)
                    with fs.open_input_stream(name) as f:
                        stack, held = np.load(io.BytesIO(f.read())), path
                crc.append(None if path is None else zlib.crc32(np.ascontiguousarray(stack[row])))
            yield pa.RecordBatch.from_arrays([*b.columns[:-2], pa.array(crc, pa.int64())], names=[*b.schema.names[:-2], "tile_crc32"])

    return index.mapInArrow(released(read), _DESCRIBED + ", tile_crc32 long")


def media_roundtrip(docs: DataFrame, folder: str | None = None, side: int = 16) -> DataFrame:
    """Store every text as an image, read the stored images back, describe them, write their NPY tiles and read those
    back. Rows as text_media() has them."""
    return read_tiles(write_tiles(store(text_media(docs), "media"), folder, side))
