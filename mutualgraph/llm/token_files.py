"""Token ids in shard files: frequency-ranked ids, byte-aligned variable-length codes, control bytes kept apart.

Format of a shard: the magic, then blocks. A block holds whole documents (at most BLOCK_IDS ids, or one longer document):
a header of seven little-endian uint64 (documents, ids, table entries, control bytes, data bytes, and two reserved), then
doc_ids (int64), null flags (uint8), lengths (uint32), the rank table (uint32: the block's distinct ids, most frequent
first), control bytes (two bits an id: its code's bytes less one, four ids a byte) and data bytes (1 to 4 each, little
endian). Each block has its own rank table, so one pass over bounded memory suffices and any block decodes alone.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import new_path, ship, store
from .tokenise import encoder
from .words import released, slices

MAGIC = b"MGTOK001"
BLOCK_IDS = 1 << 21

#: Bytes of each of the four codes that a control byte describes.
_LENGTHS = np.stack([(np.arange(256) >> (2 * k) & 3) + 1 for k in range(4)], axis=1).astype(np.uint8)


def pack_codes(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Control bytes and data bytes of unsigned 32-bit values."""
    size = 1 + (values > 0xFF).astype(np.uint8) + (values > 0xFFFF) + (values > 0xFFFFFF)
    padded = np.zeros(-(-len(values) // 4) * 4, np.uint8)
    padded[: len(values)] = size - 1
    quad = padded.reshape(-1, 4)
    control = quad[:, 0] | quad[:, 1] << 2 | quad[:, 2] << 4 | quad[:, 3] << 6
    grid = np.ascontiguousarray(values, "<u4").view(np.uint8).reshape(-1, 4)
    return control.astype(np.uint8), grid[np.arange(4) < size[:, None]]


def unpack_codes(control: np.ndarray, data: np.ndarray, n: int) -> np.ndarray:
    """Inverse of pack_codes: code lengths come from a table indexed by control byte."""
    size = _LENGTHS[control].reshape(-1)[:n].astype(np.int64)
    at = np.cumsum(size) - size
    padded = np.concatenate([data, np.zeros(3, np.uint8)])
    out = padded[at].astype(np.uint32) if n else np.zeros(0, np.uint32)
    for k in (1, 2, 3):
        more = np.flatnonzero(size > k)
        out[more] |= padded[at[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def encode_block(doc_ids: list, lengths: np.ndarray, ids: np.ndarray) -> bytes:
    found, inverse, counts = np.unique(ids, return_inverse=True, return_counts=True)
    order = np.argsort(-counts, kind="stable")
    rank = np.empty(len(order), np.uint32)
    rank[order] = np.arange(len(order), dtype=np.uint32)
    control, data = pack_codes(rank[inverse])
    null = np.array([d is None for d in doc_ids], np.uint8)
    keys = np.array([d or 0 for d in doc_ids], "<i8")
    head = np.array([len(keys), len(ids), len(found), len(control), len(data), 0, 0], "<u8")
    return b"".join(x.tobytes() for x in (head, keys, null, np.asarray(lengths, "<u4"), found[order].astype("<u4"), control, data))


def read_blocks(stream):
    """Yields (doc_ids, lengths, ids) of each block of a shard file."""
    if stream.read(len(MAGIC)) != MAGIC:
        raise ValueError("not a token shard")
    while head := stream.read(56):
        docs, n, table, controls, size, _, _ = (int(x) for x in np.frombuffer(head, "<u8"))

        def take(count, kind):
            return np.frombuffer(stream.read(count * np.dtype(kind).itemsize), kind)  # noqa: B023

        keys, null, lengths, ranks = take(docs, "<i8"), take(docs, np.uint8), take(docs, "<u4"), take(table, "<u4")
        ids = ranks[unpack_codes(take(controls, np.uint8), take(size, np.uint8), n)]
        yield [None if z else int(k) for k, z in zip(keys, null, strict=True)], lengths.astype(np.int64), ids


def open_fs(path: str):
    """The pyarrow file system of a path with or without a scheme, and the path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if ":" in path else (fs.LocalFileSystem(), path)


def write_token_shards(docs: DataFrame, tokenizer_path: str, folder: str, end_id: int = 0) -> DataFrame:
    """Tokenise `docs` (doc_id, text) in ascending doc_id order into shard files; returns the stored manifest.

    Manifest: shard, path, n_docs, n_ids, n_bytes. Null texts count as empty; each document ends with end_id; null
    doc_ids come first; rows that repeat a doc_id stand side by side. Each attempt of a task writes a file of its own and
    the manifest names those of the attempts that succeeded. Other columns are ignored.
    """
    ship(docs.sparkSession)

    def write(batches):
        task = TaskContext.get()
        fs, root = open_fs(folder)
        fs.create_dir(root, recursive=True)
        name = f"shard-{task.partitionId():06d}-{uuid.uuid4().hex}.tok"
        enc, n_docs, n_ids, n_bytes = encoder(tokenizer_path), 0, 0, len(MAGIC)
        with fs.open_output_stream(f"{root}/{name}") as out:
            out.write(MAGIC)
            for b in batches:
                for part in slices(b, "text"):
                    ids, offs = with_end(*enc.encode(part.column("text")), end_id)
                    keys, i = part.column("doc_id").to_pylist(), 0
                    while i < len(keys):
                        j = max(i + 1, int(np.searchsorted(offs, offs[i] + BLOCK_IDS, "right")) - 1)
                        out.write(block := encode_block(keys[i:j], np.diff(offs[i : j + 1]), ids[offs[i] : offs[j]]))
                        n_bytes += len(block)
                        i = j
                    n_docs, n_ids = n_docs + len(keys), n_ids + len(ids)
        if n_docs:
            yield pa.RecordBatch.from_pydict({"shard": [task.partitionId()], "path": [f"{folder}/{name}"], "n_docs": [n_docs], "n_ids": [n_ids], "n_bytes": [n_bytes]})
        else:
            fs.delete_file(f"{root}/{name}")

    dealt = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id", F.xxhash64("text"))
    rows = dealt.sortWithinPartitions("doc_id", F.xxhash64("text")).select("doc_id", "text").mapInArrow(released(write), "shard long, path string, n_docs long, n_ids long, n_bytes long")
    return store(rows, "token-manifest")


def with_end(ids: np.ndarray, offsets: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """Each row's ids followed by end_id."""
    rows = len(offsets) - 1
    new = offsets + np.arange(rows + 1)
    out = np.full(len(ids) + rows, end_id, np.uint32)
    keep = np.ones(len(out), bool)
    keep[new[1:] - 1] = False
    out[keep] = ids
    return out, new


def read_token_shards(manifest: DataFrame) -> DataFrame:
    """Per document, from the files: doc_id, start (ids of all documents before it), n_tokens, ids_crc32. Rows as
    write_token_shards() has them: repeated and null doc_ids included; an empty manifest gives an empty table."""
    # One row a shard, so this window is over shard files, not documents.
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    shards = manifest.withColumn("base", F.coalesce(F.sum("n_ids").over(before), F.lit(0)))

    def read(batches):
        for b in batches:
            for path, base in zip(b.column("path").to_pylist(), b.column("base").to_pylist(), strict=True):
                fs, name = open_fs(path)
                with fs.open_input_stream(name) as f:
                    for keys, lengths, ids in read_blocks(f):
                        ends = np.cumsum(lengths)
                        raw = ids.astype("<u4")
                        crc = [zlib.crc32(raw[e - n : e]) for e, n in zip(ends.tolist(), lengths.tolist(), strict=True)]
                        yield pa.RecordBatch.from_pydict({"doc_id": pa.array(keys, pa.int64()), "start": pa.array(base + ends - lengths), "n_tokens": pa.array(lengths), "ids_crc32": pa.array(crc, pa.int64())})
                        base += int(lengths.sum())

    count = max(1, manifest.count())
    return shards.select("path", "base").repartition(count, "path").mapInArrow(released(read), "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_shard_roundtrip(docs: DataFrame, tokenizer_path: str, folder: str | None = None, end_id: int = 0) -> DataFrame:
    """Write shard files and return what reading them back gives."""
    folder = folder or new_path(docs.sparkSession, "token-shards")
    return read_token_shards(write_token_shards(docs, tokenizer_path, folder, end_id))
