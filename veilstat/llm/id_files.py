"""Token-id files: bit- or byte-plane shuffled blocks, zstandard per plane, a chunk index.

A shard file holds the ids of consecutive documents (ascending doc_id) as fixed-size
blocks. A block of 32-bit ids is transposed into planes (four byte planes or 32 bit planes),
each compressed on its own; high planes of a small vocabulary are all zero and cost a few
bytes. Layout, little-endian:

    magic | planes of block 0 | planes of block 1 | ... | footer (zstd of JSON) | footer length, magic

The footer lists the block size, plane kind, every block's place, id count and plane sizes
(the chunk index), and the documents' ids and lengths, so that one document can be read
without the rest. Shards are written by tasks to the shared folder under a name of their
own attempt; the manifest, itself a committed table, names the attempt that counts.
"""

from __future__ import annotations

import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import raw_bytes, scratch_dir, small_batches, stage, texts_of, tidy

MAGIC = b"IDPLANE1"
BLOCK = 1 << 16
LEVEL = 3


def file_system(uri: str):
    """(pyarrow file system, path) of a Hadoop-style URI."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    if "://" not in uri:
        return fs.LocalFileSystem(), uri
    return fs.FileSystem.from_uri(uri)


def to_planes(ids: np.ndarray, kind: str) -> list[bytes]:
    """Planes of one block, lowest first."""
    octets = np.ascontiguousarray(ids.astype("<u4")).view(np.uint8).reshape(-1, 4)
    if kind == "byte":
        return [np.ascontiguousarray(octets[:, k]).tobytes() for k in range(4)]
    bits = np.unpackbits(octets, axis=1, bitorder="little")
    return [np.packbits(np.ascontiguousarray(bits[:, k]), bitorder="little").tobytes() for k in range(32)]


def from_planes(planes: list[bytes], n: int, kind: str) -> np.ndarray:
    if kind == "byte":
        octets = np.empty((n, 4), np.uint8)
        for k, p in enumerate(planes):
            octets[:, k] = np.frombuffer(p, np.uint8)
        return octets.reshape(-1).view("<u4")
    bits = np.empty((n, 32), np.uint8)
    for k, p in enumerate(planes):
        bits[:, k] = np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little")
    return np.packbits(bits, axis=1, bitorder="little").reshape(-1).view("<u4")


class ShardWriter:
    """Streams ids into blocks; holds one block and the document table."""

    def __init__(self, sink, kind: str = "byte", block: int = BLOCK):
        import zstandard

        self.sink, self.kind, self.block = sink, kind, block
        self.pack = zstandard.ZstdCompressor(level=LEVEL)
        self.held, self.n_held, self.at = [], 0, len(MAGIC)
        self.index, self.doc_ids, self.lengths = [], [], []
        sink.write(MAGIC)

    def add(self, doc_id, ids: bytes) -> None:
        self.doc_ids.append(doc_id)
        self.lengths.append(len(ids) // 4)
        self.held.append(ids)
        self.n_held += len(ids) // 4
        if self.n_held >= self.block:
            self._flush(False)

    def _flush(self, all_of_it: bool) -> None:
        ids = np.frombuffer(b"".join(self.held), "<u4")
        at = 0
        while len(ids) - at >= self.block or (all_of_it and at < len(ids)):
            one = ids[at : at + self.block]
            planes = [self.pack.compress(p) for p in to_planes(one, self.kind)]
            self.index.append([self.at, len(one), [len(p) for p in planes]])
            for p in planes:
                self.sink.write(p)
                self.at += len(p)
            at += len(one)
        self.held, self.n_held = [ids[at:].tobytes()], len(ids) - at

    def close(self) -> None:
        self._flush(True)
        foot = self.pack.compress(json.dumps({"block": self.block, "kind": self.kind, "index": self.index, "doc_ids": self.doc_ids, "lengths": self.lengths}).encode())
        self.sink.write(foot)
        self.sink.write(struct.pack("<Q", len(foot)) + MAGIC)


class ShardReader:
    """Reads a shard from a random-access file with ``seek``, ``read`` and a known size."""

    def __init__(self, source, size: int):
        import zstandard

        self.source, self.unpack = source, zstandard.ZstdDecompressor()
        source.seek(size - 16)
        tail = source.read(16)
        if tail[8:] != MAGIC:
            raise ValueError("not a shard of token ids")
        n = struct.unpack("<Q", tail[:8])[0]
        source.seek(size - 16 - n)
        self.foot = json.loads(self.unpack.decompress(source.read(n)))

    def read_block(self, k: int) -> np.ndarray:
        at, n, sizes = self.foot["index"][k]
        self.source.seek(at)
        raw = self.source.read(sum(sizes))
        planes, p = [], 0
        for s in sizes:
            planes.append(self.unpack.decompress(raw[p : p + s]))
            p += s
        return from_planes(planes, n, self.foot["kind"])

    def documents(self) -> Iterator[tuple[object, np.ndarray]]:
        """(doc_id, ids) in file order, a block in memory at a time and what a document needs."""
        k, held = 0, np.zeros(0, "<u4")
        for doc_id, n in zip(self.foot["doc_ids"], self.foot["lengths"], strict=True):
            if len(held) < n:
                parts, have = [held], len(held)
                while have < n:
                    parts.append(self.read_block(k))
                    have += len(parts[-1])
                    k += 1
                held = np.concatenate(parts)
            yield doc_id, held[:n]
            held = held[n:]

    def document(self, j: int) -> np.ndarray:
        """Ids of the shard's j-th document alone, through the chunk index."""
        first = sum(self.foot["lengths"][:j])
        n, size = self.foot["lengths"][j], self.foot["block"]
        if not n:
            return np.zeros(0, "<u4")
        ids = np.concatenate([self.read_block(k) for k in range(first // size, (first + n - 1) // size + 1)])
        return ids[first % size :][:n]


def write_ids(docs: DataFrame, path: str, folder: str, end_id: int = 1, kind: str = "byte") -> DataFrame:
    """Encode every whole text, append ``end_id``, write shards; returns the manifest (shard, path, size, n_docs, n_ids).

    Shards follow ascending doc_id (null ids first; rows that repeat an id in order of
    text, whose first characters place the cut, so that one id may take several shards); a
    null text is an empty one and has the end id alone. An empty table gives no shards;
    other columns are ignored.
    """
    from .unit_encoder import UnitEncoder

    small_batches(docs.sparkSession)
    end = np.array([end_id], "<u4").tobytes()

    def write(batches):
        encoder, writer, n_ids = UnitEncoder(path, "word"), None, 0
        task = TaskContext.get()
        for batch in batches:
            if not batch.num_rows:
                continue
            if writer is None:
                name = f"{folder}/ids-{task.partitionId():06d}-{task.attemptNumber()}-{uuid.uuid4().hex}.planes"
                store, at = file_system(name)
                store.create_dir(at.rsplit("/", 1)[0], recursive=True)
                sink = store.open_output_stream(at)
                writer = ShardWriter(sink, kind)
            doc_ids = batch.column(0).to_pylist()
            for first, ids, counts in encoder.encode_rows(*raw_bytes(texts_of(batch.column(1)))):
                stops = np.cumsum(counts)
                for k, (a, b) in enumerate(zip((stops - counts).tolist(), stops.tolist(), strict=True)):
                    writer.add(doc_ids[first + k], ids[a:b].tobytes() + end)
                n_ids += len(ids) + len(counts)
        if writer is not None:
            writer.close()
            sink.close()
            yield pa.RecordBatch.from_pylist([{"shard": task.partitionId(), "path": name, "size": store.get_file_info(at).size, "n_docs": len(writer.doc_ids), "n_ids": n_ids}])
        tidy()

    ordered = docs.select("doc_id", "text").repartitionByRange("doc_id", F.substring("text", 1, 64)).sortWithinPartitions("doc_id", "text")
    return stage(ordered.mapInArrow(write, "shard long, path string, size long, n_docs long, n_ids long"), "id-manifest")


def read_ids(manifest: DataFrame, id_type: str = "bigint") -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files alone.

    A shard's first id stands behind the ids of all shards before it: one running sum over
    the manifest, which has a row per shard.
    """
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    placed = manifest.withColumn("before", F.coalesce(F.sum("n_ids").over(before), F.lit(0))).select("path", "size", "before")

    def read(batches):
        for batch in batches:
            for row in batch.to_pylist():
                store, at = file_system(row["path"])
                ids, starts, ns, crcs, start = [], [], [], [], row["before"]
                with store.open_input_file(at) as source:
                    for doc_id, got in ShardReader(source, row["size"]).documents():
                        ids.append(doc_id)
                        starts.append(start)
                        ns.append(len(got))
                        crcs.append(zlib.crc32(got.tobytes()))
                        start += len(got)
                kind = pa.int32() if id_type == "int" else pa.int64() if id_type == "bigint" else pa.string()
                yield pa.RecordBatch.from_arrays([pa.array(ids, kind), pa.array(starts, pa.int64()), pa.array(ns, pa.int64()), pa.array(crcs, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])
        tidy()

    shards = max(1, manifest.count())
    return placed.repartition(shards, "path").mapInArrow(read, f"doc_id {id_type}, start long, n_tokens long, ids_crc32 long")


def id_file_digest(docs: DataFrame, path: str, end_id: int = 1, kind: str = "byte") -> DataFrame:
    """Write the id files of ``docs`` to the shared folder, read them back, one row per document.

    Null texts, null or repeated ids, empty tables and other columns are as in ``write_ids``.
    """
    folder = f"{scratch_dir(docs.sparkSession)}/ids-{uuid.uuid4().hex}"
    return read_ids(write_ids(docs, path, folder, end_id, kind), docs.schema["doc_id"].dataType.simpleString())
