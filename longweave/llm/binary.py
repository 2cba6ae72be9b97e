"""Token ids in bit-plane files: blocks of ids are transposed into bit planes, each plane compressed, chunks indexed.

File: the magic, then for each chunk of BLOCK ids its planes one after another (plane 0 is the lowest bit; a plane of
zeros only takes no bytes), then the index, the index's length and the magic again.  The index (zstandard, JSON) holds
each chunk's place, number of ids and plane lengths, and each document's id and number of ids.
"""

from __future__ import annotations

import json
import struct
from collections.abc import Iterable, Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import column, cut, table, tasks
from longweave.llm.files import Publish, new_folder, open_store
from longweave.llm.tokens import END_ID, crc, default_path, ids_of

MAGIC, BLOCK, LEVEL = b"LWBP0001", 1 << 16, 1
END = np.array([END_ID], dtype="<u4").tobytes()


def to_planes(ids: np.ndarray) -> list[bytes]:
    """Bit planes of unsigned 32-bit ids, the lowest first; only as many as the largest id needs."""
    width = max(1, int(ids.max()).bit_length()) if len(ids) else 1
    return [np.packbits(((ids >> np.uint32(j)) & np.uint32(1)).astype(np.uint8), bitorder="little").tobytes() for j in range(width)]


def from_planes(planes: list[bytes], n: int) -> np.ndarray:
    out = np.zeros(n, dtype="<u4")
    for j, p in enumerate(planes):
        if p:
            out |= np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little").astype("<u4") << np.uint32(j)
    return out


class PlaneWriter:
    """Streams documents into one file; holds one chunk of ids and the index."""

    def __init__(self, out):
        self.out, self.zip, self.held, self.n = out, zstandard.ZstdCompressor(level=LEVEL), [], 0
        self.chunks: list[list] = []
        self.docs: list[list[int | None]] = []
        out.write(MAGIC)
        self.at = len(MAGIC)

    def add(self, doc_id: int | None, ids: bytes) -> None:
        self.docs.append([doc_id, len(ids) // 4])
        self.held.append(ids)
        self.n += len(ids) // 4
        if self.n >= BLOCK:
            whole = b"".join(self.held)
            for i in range(0, self.n - BLOCK + 1, BLOCK):
                self._chunk(np.frombuffer(whole, "<u4", BLOCK, 4 * i))
            self.held, self.n = [whole[4 * (self.n - self.n % BLOCK) :]], self.n % BLOCK

    def _chunk(self, ids: np.ndarray) -> None:
        planes = [self.zip.compress(p) if any(p) else b"" for p in to_planes(ids)]
        self.chunks.append([self.at, len(ids), [len(p) for p in planes]])
        for p in planes:
            self.out.write(p)
            self.at += len(p)

    def close(self) -> None:
        if self.n:
            self._chunk(np.frombuffer(b"".join(self.held), "<u4"))
        index = self.zip.compress(json.dumps({"block": BLOCK, "chunks": self.chunks, "docs": self.docs}).encode())
        self.out.write(index + struct.pack("<Q", len(index)) + MAGIC)


class PlaneReader:
    """Random access to a plane file: any document's ids from the chunks that hold them."""

    def __init__(self, uri: str):
        store, path = open_store(uri)
        self.f = store.open_input_file(path)
        size = self.f.size()
        tail = self._at(size - 16, 16)
        if tail[8:] != MAGIC or self._at(0, 8) != MAGIC:
            raise ValueError(f"{uri} is no plane file")
        n = struct.unpack("<Q", tail[:8])[0]
        self.index = json.loads(zstandard.ZstdDecompressor().decompress(self._at(size - 16 - n, n)))
        self.docs = self.index["docs"]
        self.starts = [0, *accumulate(d[1] for d in self.docs)]
        self._last = (-1, np.empty(0, "<u4"))

    def _at(self, at: int, n: int) -> bytes:
        self.f.seek(at)
        return self.f.read(n)

    def chunk(self, k: int) -> np.ndarray:
        if self._last[0] != k:
            at, n, sizes = self.index["chunks"][k]
            raw, unzip, place, planes = self._at(at, sum(sizes)), zstandard.ZstdDecompressor(), 0, []
            for s in sizes:
                planes.append(unzip.decompress(raw[place : place + s], max_output_size=n // 8 + 1) if s else b"")
                place += s
            self._last = k, from_planes(planes, n)
        return self._last[1]

    def read(self, i: int) -> np.ndarray:
        """Ids of the file's document number i."""
        a, z, b = self.starts[i], self.starts[i + 1], self.index["block"]
        parts = [self.chunk(k)[max(0, a - k * b) : z - k * b] for k in range(a // b, -(-z // b))]
        return np.concatenate(parts) if parts else np.empty(0, "<u4")


def write_token_files(docs: DataFrame, folder: str, tokenizer_path: str, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One file for each range of ids, documents in ascending order (null ids first; equal ids by text).

    Returns the manifest: part, uri, n_docs, n_ids, bytes; one row per file, in order of part.
    Null texts are empty documents (only the end id).  An empty table gives no files.
    """
    spark = docs.sparkSession
    body = docs.select(column(docs, id_col, "long").alias("doc_id"), F.coalesce(column(docs, text, "string"), F.lit("")).alias("text"))
    ordered = body.repartitionByRange(tasks(spark, 12), "doc_id").sortWithinPartitions("doc_id", "text")

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, out, writer, n_docs, n_ids = TaskContext.get().partitionId(), None, None, 0, 0
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                rows = batch.slice(at, 256)
                for doc_id, ids in zip(rows.column(0).to_pylist(), ids_of(rows.column(1).to_pylist(), tokenizer_path), strict=True):
                    if writer is None:
                        out = Publish(f"{folder}/part-{part:06d}.planes")
                        writer = PlaneWriter(out)
                    writer.add(doc_id, ids + END)
                    n_docs, n_ids = n_docs + 1, n_ids + len(ids) // 4 + 1
        if writer is not None:
            writer.close()
            out.publish()
            yield pa.RecordBatch.from_pydict({"part": [part], "uri": [f"{folder}/part-{part:06d}.planes"], "n_docs": [n_docs], "n_ids": [n_ids], "bytes": [out.size]})

    return cut(ordered.mapInArrow(write, "part long, uri string, n_docs long, n_ids long, bytes long"))


def read_token_files(manifest: DataFrame, with_ids: bool = True) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids_crc32 and ids (little-endian bytes), from the files."""
    spark = manifest.sparkSession
    sums, total = [], 0
    for r in manifest.select("part", "uri", "n_ids").orderBy("part").collect():  # one row per file
        sums.append((r["part"], r["uri"], total))
        total += r["n_ids"]
    placed = spark.createDataFrame(sums, "part long, uri string, before long").repartition(max(1, len(sums)), "part")

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                f = PlaneReader(row["uri"])
                for at in range(0, len(f.docs), 512):
                    n = range(at, min(at + 512, len(f.docs)))
                    ids = [f.read(i).tobytes() for i in n]
                    cols = [pa.array([f.docs[i][0] for i in n], pa.int64()), pa.array([row["before"] + f.starts[i] for i in n], pa.int64()), pa.array([f.docs[i][1] for i in n], pa.int64()), pa.array(list(map(crc, ids)), pa.int64()), pa.array(ids, pa.binary())]
                    yield pa.RecordBatch.from_arrays(cols[: 4 + with_ids], ["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: 4 + with_ids])

    return placed.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids)


def op10_token_binary(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    manifest = write_token_files(docs, new_folder(spark, "token-planes"), default_path())
    return read_token_files(manifest, with_ids=False)
