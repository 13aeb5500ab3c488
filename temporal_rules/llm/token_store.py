"""Token files: every document's ids compressed by themselves under one shared dictionary.

A store is a folder of shards ``part-00000.tok`` in ascending doc_id order and one dictionary
file.  A shard is

    magic "TOKD0001" | width of an id (u8) | 32 bytes sha-256 of the dictionary
    one zstandard frame for each document, over its ids (little endian)
    index: doc_id i64[n] | frame offset u64[n+1] | ids u32[n]
    offset of the index u64 | n u64 | magic

so one document is read with the index and a single range read, whatever the shard's size.
The dictionary is trained once on the serialised ids of a bounded sample of documents
(``sample_docs``, the least hashed doc_ids); every document is encoded and stored.
"""

from __future__ import annotations

import hashlib
import io
import struct
import uuid
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, forget, reach_workers, staged

MAGIC = b"TOKD0001"
BATCH = 10 << 20  # bytes of text encoded at once
NO_ID = -(1 << 63)  # stands for a null doc_id in an index; sorts first, as nulls do


def open_fs(path: str):
    from pyarrow import fs

    if "://" in path or path.startswith("file:"):
        got, inner = fs.FileSystem.from_uri(path.replace("file:/", "file:///", 1) if path.startswith("file:/") and not path.startswith("file://") else path)
        return got, inner
    return fs.LocalFileSystem(), path


def train_dictionary(samples: list[bytes], size: int) -> bytes:
    """A zstandard dictionary; with too few samples to train on, their own bytes serve as one."""
    import zstandard

    samples = [s for s in samples if s]
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


def _as_dict(raw: bytes):
    import zstandard

    return zstandard.ZstdCompressionDict(raw) if raw else None


def _compressor(raw: bytes, level: int):
    import zstandard

    return zstandard.ZstdCompressor(level=level, dict_data=_as_dict(raw), write_checksum=False, write_dict_id=False)


def _decompressor(raw: bytes):
    import zstandard

    return zstandard.ZstdDecompressor(dict_data=_as_dict(raw))


@dataclass(frozen=True)
class TokenStore:
    """A written store: shard names with their documents and ids, in order, and the dictionary."""

    path: str
    dictionary_hash: str
    shards: list[tuple[str, int, int]]

    def documents(self, spark: SparkSession) -> DataFrame:
        """Every document as the files hold it: doc_id, start, n_tokens, ids_crc32."""
        return read_store(spark, self)


def write_store(docs: DataFrame, tokenizer: str, end_id: int, text: str = "text", doc_id: str = "doc_id", sample_docs: int = 1000, dictionary_bytes: int = 64 << 10, level: int = 1, shard_bytes: int = 128 << 20) -> TokenStore:
    """Encode all documents and write a store in the shared folder.

    Null texts are empty; every document ends with ``end_id``; null doc_ids come first and
    repeated ones stay, in the order of a hash of their frames, and may go on in the next shard.  Shards hold about
    ``shard_bytes`` each.  An empty table gives a store without shards.  Other columns
    of ``docs`` are ignored.  Texts are encoded before the shuffle, so what moves is compressed.
    """
    from .tokens import by_bytes, encoder

    spark = docs.sparkSession
    reach_workers(spark, 10_000, BATCH)  # large batches: a word met twice in one is looked up once
    docs = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    # The sample is chosen by ids alone, so its sort does not carry texts; at most sample_docs ids are broadcast.
    chosen = docs.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs)
    sample = docs.join(F.broadcast(chosen), "doc_id", "left_semi")

    def serialised(batches):
        for batch in batches:
            enc = encoder(tokenizer)
            ids, off = enc.encode(batch.column(0))
            yield pa.record_batch([pa.array([ids[a:b].tobytes() for a, b in zip(off, off[1:])], pa.binary())], ["raw"])

    raw = [bytes(r["raw"]) for r in sample.select("text").mapInArrow(serialised, "raw binary").collect()]
    dictionary = train_dictionary(raw, dictionary_bytes)
    digest = hashlib.sha256(dictionary).digest()
    path = fresh_path(spark, "tokens")
    fs, folder = open_fs(path)
    fs.create_dir(folder, recursive=True)
    with fs.open_output_stream(f"{folder}/dictionary.zdict") as f:
        f.write(dictionary)

    def frames(batches):
        enc, comp = encoder(tokenizer), _compressor(dictionary, level)
        for batch in batches:
            for part in by_bytes(batch, 1, BATCH):
                ids, off = enc.encode(part.column(1), BATCH)
                end = np.array([end_id], ids.dtype).tobytes()
                blobs = [comp.compress(ids[a:b].tobytes() + end) for a, b in zip(off.tolist(), off[1:].tolist())]
                yield pa.record_batch([part.column(0), pa.array(np.diff(off) + 1, pa.int64()), pa.array(blobs, pa.binary())], ["doc_id", "n", "frame"])

    coded = staged(docs.mapInArrow(frames, "doc_id long, n long, frame binary"), "frames")
    size = coded.agg(F.sum(F.length("frame") + 20).alias("n")).first()["n"] or 0
    shards = max(1, -(-size // shard_bytes))
    width = np.dtype(encoder(tokenizer).type).itemsize
    def written(batches):
        from pyspark import TaskContext

        ids, sizes, at = [], [], [len(MAGIC) + 33]
        which, out, name = None, None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            if out is None:
                which = TaskContext.get().partitionId()
                name = f"part-{which:05d}.tok"
                fs_, folder_ = open_fs(path)
                tmp = f"{folder_}/.{name}-{uuid.uuid4().hex}"
                out = fs_.open_output_stream(tmp)
                out.write(MAGIC + bytes([width]) + digest)
            got = batch.column(2).to_pylist()
            out.write(b"".join(got))
            at += (at[-1] + np.cumsum([len(x) for x in got])).tolist()
            ids += [NO_ID if x is None else x for x in batch.column(0).to_pylist()]
            sizes += batch.column(1).to_pylist()
        if out is not None:
            out.write(np.array(ids, "<i8").tobytes() + np.array(at, "<u8").tobytes() + np.array(sizes, "<u4").tobytes())
            out.write(struct.pack("<QQ", at[-1], len(ids)) + MAGIC)
            out.close()
            fs_.move(tmp, f"{folder_}/{name}")  # a repeated task replaces the same shard whole
            yield pa.record_batch([pa.array([which], pa.int64()), pa.array([name]), pa.array([len(ids)], pa.int64()), pa.array([sum(sizes)], pa.int64())], ["shard", "name", "docs", "ids"])

    # Ranges of (doc_id, hash), found by a sample and looked up by search, so a doc_id of very many rows is several shards.
    dealt = coded.select("doc_id", "n", "frame", F.xxhash64("frame").alias("h")).repartitionByRange(shards, F.asc_nulls_first("doc_id"), "h")
    made = dealt.sortWithinPartitions(F.asc_nulls_first("doc_id"), "h", "frame").select("doc_id", "n", "frame").mapInArrow(written, "shard long, name string, docs long, ids long").collect()
    forget(coded)
    return TokenStore(path, digest.hex(), [(r["name"], r["docs"], r["ids"]) for r in sorted(made, key=lambda r: r["shard"])])


def _index(f) -> tuple[int, bytes, np.ndarray, np.ndarray, np.ndarray]:
    size = f.size()
    tail = f.read_at(24, size - 24)
    at, n = struct.unpack("<QQ", tail[:16])
    head = f.read_at(len(MAGIC) + 33, 0)
    if tail[16:] != MAGIC or head[:8] != MAGIC:
        raise ValueError("not a token shard")
    raw = f.read_at(size - 24 - at, at)
    ids = np.frombuffer(raw, "<i8", n)
    offsets = np.frombuffer(raw, "<u8", n + 1, 8 * n)
    sizes = np.frombuffer(raw, "<u4", n, 16 * n + 8)
    return head[8], head[9:41], ids, offsets, sizes


def _dictionary(fs, folder: str, digest: bytes) -> bytes:
    with fs.open_input_stream(f"{folder}/dictionary.zdict") as f:
        raw = f.read()
    if hashlib.sha256(raw).digest() != digest:
        raise ValueError("the shard was written under another dictionary")
    return raw


def read_document(path: str, shard: str, doc_id: int) -> list[list[int]]:
    """The ids of one document (of each copy in the shard, if a doc_id is repeated), without reading the rest of the shard."""
    fs, folder = open_fs(path)
    with fs.open_input_file(f"{folder}/{shard}") as f:
        width, digest, ids, offsets, sizes = _index(f)
        lo, hi = np.searchsorted(ids, doc_id), np.searchsorted(ids, doc_id, side="right")
        undo = _decompressor(_dictionary(fs, folder, digest))
        frames = [f.read_at(int(offsets[i + 1] - offsets[i]), int(offsets[i])) for i in range(lo, hi)]
    return [np.frombuffer(undo.decompress(x, max_output_size=int(sizes[i]) * width), f"<u{width}").tolist() for x, i in zip(frames, range(lo, hi))]


def read_store(spark: SparkSession, store: TokenStore) -> DataFrame:
    """doc_id, start (ids of all documents before), n_tokens, ids_crc32, read back from the files."""
    path = store.path
    bases, base = [], 0
    for name, _, n in store.shards:
        bases.append((name, base))
        base += n

    def rows(batches):
        for batch in batches:
            for name, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                fs, folder = open_fs(path)
                with fs.open_input_file(f"{folder}/{name}") as f:
                    width, digest, ids, offsets, sizes = _index(f)
                    undo = _decompressor(_dictionary(fs, folder, digest))
                    start = base + np.cumsum(sizes.astype(np.int64)) - sizes
                    for lo in range(0, len(ids), 2048):
                        hi = min(len(ids), lo + 2048)
                        raw = io.BytesIO(f.read_at(int(offsets[hi] - offsets[lo]), int(offsets[lo])))
                        crc = []
                        for i in range(lo, hi):
                            one = np.frombuffer(undo.decompress(raw.read(int(offsets[i + 1] - offsets[i])), max_output_size=int(sizes[i]) * width), f"<u{width}")
                            if len(one) != sizes[i]:
                                raise ValueError(f"document {ids[i]} of {name} is not whole")
                            crc.append(zlib.crc32(one.astype("<u4").tobytes()))
                        yield pa.record_batch([pa.array(ids[lo:hi], mask=ids[lo:hi] == NO_ID), pa.array(start[lo:hi]), pa.array(sizes[lo:hi].astype(np.int64)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    files = spark.createDataFrame(bases, "name string, base long")
    if len(bases) > 1:
        files = files.repartition(len(bases), "name")
    return files.mapInArrow(rows, "doc_id long, start long, n_tokens long, ids_crc32 long")
