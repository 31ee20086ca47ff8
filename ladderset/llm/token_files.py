"""Token-id files: fixed-size id blocks shuffled into byte or bit planes, each plane under zstandard, with a chunk index.

A shard is one self-contained byte image:

    magic "LSPLANE1" | blocks | chunk index | document index | footer

A block holds up to `block` ids. Its ids are transposed: plane j of a byte-plane block is the j-th byte of
every id, of a bit-plane block the j-th bit, eight ids to a byte. Planes that are all zero take no room.
The chunk index (compressed) has, for each block, the number of ids and the size of every plane, so any
token range is read by decoding only the blocks it touches. The document index has doc_ids and lengths.
The footer is fixed in size: where both indexes lie, counts, and a crc32 of all before it.

Shards are rows of a Parquet table written by Spark's committer (one binary image a row, with its place
and counts as columns). That keeps the write atomic on any store that Spark can write, whatever
executors are lost; `shard_image` and `Shard` work on plain bytes for anyone who wants single files.

Defined cases: null text is an empty document (its ids are the end id alone); rows that repeat a doc_id
stay and lie next to each other; a null doc_id comes first and is read back as null; an empty table gives an empty table
of shards; further columns of the input are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .support import Scratch, table
from .tokenids import crc32s, encoder, vocabulary

MAGIC = b"LSPLANE1"
FOOTER = struct.Struct("<QQQQQIBI8s")
BLOCK = 1 << 16
SHARD_TOKENS = 1 << 20
NO_ID = -(2**63)


def to_planes(ids: np.ndarray, bits: bool) -> list[bytes]:
    """The planes of one block; empty bytes stand for a plane of zeros."""
    raw = np.ascontiguousarray(ids, "<u4").view(np.uint8).reshape(-1, 4)
    if bits:
        planes = np.packbits(np.unpackbits(raw, axis=1, bitorder="little").T, axis=1, bitorder="little")
    else:
        planes = np.ascontiguousarray(raw.T)
    return [p.tobytes() if p.any() else b"" for p in planes]


def from_planes(planes: list[bytes], n: int, bits: bool) -> np.ndarray:
    if bits:
        flags = np.zeros((32, n), np.uint8)
        for j, p in enumerate(planes):
            if p:
                flags[j] = np.unpackbits(np.frombuffer(p, np.uint8), bitorder="little")[:n]
        raw = np.packbits(np.ascontiguousarray(flags.T), axis=1, bitorder="little")
    else:
        raw = np.zeros((n, 4), np.uint8)
        for j, p in enumerate(planes):
            if p:
                raw[:, j] = np.frombuffer(p, np.uint8)
    return np.ascontiguousarray(raw).view("<u4").ravel()


def shard_image(doc_ids: np.ndarray, lengths: np.ndarray, ids: np.ndarray, block: int = BLOCK, planes: str = "byte", level: int = 3) -> bytes:
    """The bytes of one shard."""
    bits, pack = planes == "bit", zstandard.ZstdCompressor(level=level).compress
    body, index = [MAGIC], []
    for lo in range(0, len(ids), block):
        part = ids[lo : lo + block]
        packed = [pack(p) if p else b"" for p in to_planes(part, bits)]
        index.append([len(part), *map(len, packed)])
        body += packed
    chunk = pack(np.asarray(index, "<u4").tobytes())
    docs = pack(np.asarray(doc_ids, "<i8").tobytes() + np.asarray(lengths, "<u4").tobytes())
    head = b"".join(body)
    front = head + chunk + docs
    return front + FOOTER.pack(len(head), len(chunk), len(docs), len(ids), len(doc_ids), block, bits, zlib.crc32(front), MAGIC)


class Shard:
    """Reads a shard image: all of it, or any token range."""

    def __init__(self, image: bytes):
        if len(image) < FOOTER.size or image[:8] != MAGIC:
            raise ValueError("not a token shard")
        head, chunk, docs, self.n_tokens, n_docs, self.block, bits, crc, magic = FOOTER.unpack(image[-FOOTER.size :])
        if magic != MAGIC or head + chunk + docs + FOOTER.size != len(image) or zlib.crc32(memoryview(image)[: -FOOTER.size]) != crc:
            raise ValueError("damaged token shard")
        self.image, self.bits, self.unpack = image, bool(bits), zstandard.ZstdDecompressor().decompress
        self.index = np.frombuffer(self.unpack(image[head : head + chunk]), "<u4").reshape(-1, 33 if bits else 5)
        raw = self.unpack(image[head + chunk : head + chunk + docs])
        self.doc_ids, self.lengths = np.frombuffer(raw, "<i8", n_docs), np.frombuffer(raw, "<u4", n_docs, 8 * n_docs)
        self.begin = 8 + np.concatenate([[0], np.cumsum(self.index[:, 1:].sum(1, dtype=np.int64))])

    def _block(self, k: int) -> np.ndarray:
        sizes = self.index[k, 1:].astype(np.int64)
        at = self.begin[k] + np.cumsum(sizes) - sizes
        return from_planes([self.unpack(self.image[a : a + s]) if s else b"" for a, s in zip(at.tolist(), sizes.tolist(), strict=True)], int(self.index[k, 0]), self.bits)

    def tokens(self, lo: int = 0, hi: int | None = None) -> np.ndarray:
        hi = self.n_tokens if hi is None else min(hi, self.n_tokens)
        if lo >= hi:
            return np.empty(0, "<u4")
        first = lo // self.block
        parts = [self._block(k) for k in range(first, -(-hi // self.block))]
        return np.concatenate(parts)[lo - first * self.block : hi - first * self.block]


SHARDS = "part int, seq int, n_docs long, n_tokens long, image binary"


def write_token_files(
    docs: DataFrame, path: str, tokenizer: str, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, shard_tokens: int = SHARD_TOKENS, planes: str = "byte"
) -> None:
    """Encodes all documents in ascending doc_id order and writes the shards; a shard is closed once it has `shard_tokens` ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, seq = encoder(tokenizer, end_id), TaskContext.get().partitionId(), 0
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def close() -> pa.RecordBatch:
            nonlocal seq, size
            d, n, x = (np.concatenate(c) for c in zip(*held, strict=True))
            row = [[part], [seq], [len(d)], [len(x)], [shard_image(d, n, x, block, planes)]]
            held.clear()
            seq, size = seq + 1, 0
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)], ["part", "seq", "n_docs", "n_tokens", "image"])

        for batch in batches:
            doc = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
            for lo, hi, ids, at in enc.batches(batch):
                i, n = 0, hi - lo
                while i < n:
                    j = min(n, max(i + 1, int(np.searchsorted(at, at[i] + shard_tokens - size, "right")) - 1))
                    held.append((doc[lo + i : lo + j], np.diff(at[i : j + 1]), ids[at[i] : at[j]]))
                    size, i = size + int(at[j] - at[i]), j
                    if size >= shard_tokens or i < n:
                        yield close()
        if held:
            yield close()

    chosen = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    chosen.repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.xxhash64("text")).mapInArrow(run, SHARDS).write.parquet(path)


def read_token_files(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """One row per document: doc_id, start (ids before it in the whole table), n_tokens, ids_crc32, and the ids if asked for."""
    shards = spark.read.schema(SHARDS).parquet(path)
    # counts of parts are as many rows as the writing job had tasks; the running sum over them is small by that bound
    parts = shards.groupBy("part").agg(F.sum("n_tokens").alias("n")).select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("part_start"))
    place = (
        shards.select("part", "seq", (F.sum("n_tokens").over(Window.partitionBy("part").orderBy("seq")) - F.col("n_tokens")).alias("seq_start"))
        .join(parts, "part")
        .select("part", "seq", (F.col("part_start") + F.col("seq_start")).alias("shard_start"))
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, seq, image in zip(*(batch.column(c).to_pylist() for c in ("part", "seq", "image")), strict=True):
                s = Shard(image)
                ids = s.tokens()
                at = np.concatenate([[0], np.cumsum(s.lengths, dtype=np.int64)])
                n = len(s.doc_ids)
                cols = [pa.array(np.full(n, part, np.int32)), pa.array(np.full(n, seq, np.int32)), pa.array(s.doc_ids, mask=s.doc_ids == NO_ID), pa.array(at[:-1]), pa.array(np.diff(at)), pa.array(crc32s(ids, at))]
                names = ["part", "seq", "doc_id", "inside", "n_tokens", "ids_crc32"]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids.astype(np.int64))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names)

    out = "part int, seq int, doc_id long, inside long, n_tokens long, ids_crc32 long" + (", ids array<long>" if with_ids else "")
    rows = shards.select("part", "seq", "image").mapInArrow(run, out)
    return rows.join(place, ["part", "seq"]).select("doc_id", (F.col("shard_start") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32", *(["ids"] if with_ids else []))


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = Scratch(spark, "token-files").new_path("shards")
    write_token_files(table(spark, sf_dir, "documents"), path, vocabulary())
    return read_token_files(spark, path)
