"""Token files of shuffled planes.

A shard holds the ids of consecutive documents as one run of 32-bit integers, cut into blocks of a fixed number of ids. Each
block is transposed into byte planes (or bit planes), each plane compressed with zstandard by itself; the shard ends with an
index of its blocks and a table of its documents, so that any document can be read without the blocks before it.

Shards are written through Spark's own writers, as rows (shard, number, content): whatever store Spark reaches can hold them, a
lost or repeated task leaves nothing behind, and ``content`` is the file, byte for byte.

Defined results: a null text has the end id only; rows with the same id are ordered by their text, null ids go with 0; texts
of any length are written whole, over as many blocks as they need; an empty table gives no shard and an empty result.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common, ordered, tokens

MAGIC = b"planes01"
BLOCK_IDS = 1 << 16
#: Ids after which a task begins a new shard.
SHARD_IDS = 1 << 22
LEVEL = 1
BYTE, BIT = 8, 32  # kinds of planes: 4 of bytes, or 32 of bits


def shuffle(ids: np.ndarray, kind: int) -> list[bytes]:
    """The planes of one block."""
    if kind == BYTE:
        return [x.tobytes() for x in ids.astype("<u4", copy=False).view(np.uint8).reshape(-1, 4).T]
    bits = np.unpackbits(ids.astype("<u4", copy=False).view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")
    return [np.packbits(x, bitorder="little").tobytes() for x in bits.T]


def unshuffle(planes: list[bytes], n: int, kind: int) -> np.ndarray:
    if kind == BYTE:
        return np.ascontiguousarray(np.stack([np.frombuffer(p, np.uint8, n) for p in planes], axis=1)).view("<u4").reshape(-1)
    bits = np.stack([np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little") for p in planes], axis=1)
    return np.packbits(bits, axis=1, bitorder="little").view("<u4").reshape(-1)


def write_shard(ids: np.ndarray, doc_ids: list[int | None], lengths: list[int], block: int = BLOCK_IDS, kind: int = BYTE, level: int = LEVEL) -> bytes:
    packer = zstandard.ZstdCompressor(level=level)
    out, index = bytearray(MAGIC), []
    for at in range(0, len(ids), block):
        part = ids[at : at + block]
        planes = [packer.compress(p) for p in shuffle(part, kind)]
        index.append((len(out), len(part), *map(len, planes)))
        for p in planes:
            out += p
    n_planes = 4 if kind == BYTE else 32
    table = struct.pack("<IIII", kind, block, len(index), len(doc_ids))
    table += np.array(index, "<u8").reshape(-1, 2 + n_planes).tobytes()
    table += np.array([0 if d is None else d for d in doc_ids], "<i8").tobytes() + np.array([d is None for d in doc_ids], "u1").tobytes() + np.array(lengths, "<u8").tobytes()
    out += table + struct.pack("<Q", len(table)) + MAGIC
    return bytes(out)


class Shard:
    """Reads one shard: its index first, blocks when asked for."""

    def __init__(self, data: bytes):
        if data[:8] != MAGIC or data[-8:] != MAGIC:
            raise ValueError("no shard, or one that is cut short")
        (size,) = struct.unpack_from("<Q", data, len(data) - 16)
        at = len(data) - 16 - size
        self.kind, self.block, blocks, docs = struct.unpack_from("<IIII", data, at)
        at += 16
        wide = 2 + (4 if self.kind == BYTE else 32)
        self.index = np.frombuffer(data, "<u8", blocks * wide, at).reshape(blocks, wide)
        at += self.index.nbytes
        ids = np.frombuffer(data, "<i8", docs, at).tolist()
        none = np.frombuffer(data, "u1", docs, at + 8 * docs)
        self.doc_ids = [None if gone else i for i, gone in zip(ids, none, strict=True)]
        self.lengths = np.frombuffer(data, "<u8", docs, at + 9 * docs).astype(np.int64)
        self.starts = np.concatenate(([0], np.cumsum(self.lengths)))[:-1]
        self.data, self.reader, self._held = data, zstandard.ZstdDecompressor(), (-1, None)

    def block_ids(self, k: int) -> np.ndarray:
        if self._held[0] != k:
            at, n, *sizes = map(int, self.index[k])
            planes = []
            for size in sizes:
                planes.append(self.reader.decompress(self.data[at : at + size]))
                at += size
            self._held = (k, unshuffle(planes, n, self.kind))
        return self._held[1]

    def read(self, start: int, n: int) -> np.ndarray:
        """ids start .. start + n of the shard."""
        parts = []
        while n > 0:
            k, off = divmod(start, self.block)
            got = self.block_ids(k)[off : off + n]
            parts.append(got)
            start, n = start + len(got), n - len(got)
        return np.concatenate(parts) if len(parts) != 1 else parts[0]


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def shards(docs: DataFrame, path: str | None = None, end_id: int = 2, kind: int = BYTE, block: int = BLOCK_IDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """part, shard, n_ids, content: ids of all documents in ascending id order; shards are ordered by (part, shard)."""
    path = path or default_path()

    def pack(batches):
        from pyspark import TaskContext

        coder = tokens.worker_cache(("bytes", path), lambda: tokens.ByteCoder(path))
        part, number, end = TaskContext.get().partitionId(), 0, np.array([end_id], "<u4").tobytes()
        held, doc_ids, lengths, n = [], [], [], 0
        for pdf in batches:
            for doc_id, gone, ids in zip(pdf["doc_id"], pdf["gone"], coder.encode_each(pdf["text"]), strict=True):
                ids += end
                held.append(ids)
                doc_ids.append(None if gone else int(doc_id))
                lengths.append(len(ids) // 4)
                n += lengths[-1]
                if n >= SHARD_IDS:
                    yield pd.DataFrame([(part, number, n, write_shard(np.frombuffer(b"".join(held), "<u4"), doc_ids, lengths, block, kind))], columns=["part", "shard", "n_ids", "content"])
                    held, doc_ids, lengths, n, number = [], [], [], 0, number + 1
        if doc_ids:
            yield pd.DataFrame([(part, number, n, write_shard(np.frombuffer(b"".join(held), "<u4"), doc_ids, lengths, block, kind))], columns=["part", "shard", "n_ids", "content"])

    rows = docs.select(*common.id_and_gone(id_col), common.whole_text(docs, text_col).alias("text"))
    return ordered.in_order(rows, "doc_id", "gone", "text").mapInPandas(pack, "part int, shard int, n_ids long, content binary")


READ = "part int, shard int, doc_id long, at long, n_tokens long, ids_crc32 long"


def read_back(written: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the shards."""

    def unpack(batches):
        for pdf in batches:
            for part, number, content in pdf[["part", "shard", "content"]].itertuples(index=False, name=None):
                shard = Shard(content)
                rows = [(part, number, d, s, n, zlib.crc32(np.ascontiguousarray(shard.read(s, n), "<u4").tobytes())) for d, s, n in zip(shard.doc_ids, shard.starts.tolist(), shard.lengths.tolist(), strict=True)]
                yield common.frame(rows, READ)

    each = written.select("part", "shard", "content").mapInPandas(unpack, READ)
    # one short row per shard: where it begins among all ids
    order = Window.orderBy("part", "shard").rowsBetween(Window.unboundedPreceding, -1)
    begins = written.select("part", "shard", "n_ids").withColumn("begin", F.coalesce(F.sum("n_ids").over(order), F.lit(0))).drop("n_ids")
    return each.join(begins, ["part", "shard"]).select("doc_id", (F.col("begin") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def op10_plane_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_back(common.keep(shards(common.documents(spark, sf_dir)), "shards"))
