"""WARC archives of zstandard frames: one frame per record, with a dictionary in a leading skippable frame.

File: the skippable frame (magic 0x184D2A5D, length, the raw dictionary), a warcinfo record, then the records.  The
dictionary is trained on at most SAMPLE payloads (those of the smallest page_id hash), each cut to SAMPLE_BYTES.
A payload of at least MIN_DEDUP bytes that occurs in several rows is stored with its smallest page_id (all rows of that
page_id); the others are revisit records that name it.
Null payloads are empty; null urls are written as empty; rows whose page_id is null never serve as a response of others.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Iterable, Iterator
from uuid import UUID

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import column, cut, hash_sample, table, tasks
from longweave.llm.files import Publish, new_folder, open_store

SKIP_MAGIC, MIN_DEDUP, SAMPLE, SAMPLE_BYTES, DICT_BYTES, LEVEL = 0x184D2A5D, 100, 2000, 16_384, 1 << 16, 3
FILE_BYTES = 1 << 28
DATE = "2024-01-01T00:00:00Z"


def train_dictionary(pages: DataFrame, payload: str = "html", sample: int = SAMPLE) -> bytes:
    """Empty where there is too little to train on."""
    rows = hash_sample(pages, column(pages, "page_id", "long"), sample).select(F.substring(F.coalesce(column(pages, payload, "string"), F.lit("")), 1, SAMPLE_BYTES).alias("t")).collect()
    try:
        return zstandard.train_dictionary(DICT_BYTES, [r["t"].encode("utf-8", "surrogatepass") for r in rows if r["t"]]).as_bytes()
    except zstandard.ZstdError:
        return b""


def record(page_id: int | None, url: str, kind: str, digest: str, size: int, refers: int | None, body: bytes) -> bytes:
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{UUID(bytes=hashlib.md5(f'{page_id}|{url}|{digest}'.encode()).digest())}>",
        f"WARC-Date: {DATE}", f"WARC-Target-URI: {' '.join(url.split())}", f"WARC-Payload-Digest: sha256:{digest}",
        f"X-Page-Id: {'' if page_id is None else page_id}", f"X-Payload-Length: {size}",
    ]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"X-Refers-To-Page: {refers}"]
    head += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = raw.partition(b"\r\n\r\n")
    named = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in head.decode().split("\r\n")[1:])
    return named, rest[: int(named["Content-Length"])]


class WarcWriter:
    def __init__(self, uri: str, dictionary: bytes):
        self.uri, self.out, self.n = uri, Publish(uri), 0
        self.zip = zstandard.ZstdCompressor(level=LEVEL, dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None)
        self.out.write(struct.pack("<II", SKIP_MAGIC, len(dictionary)) + dictionary)
        self.out.write(self.zip.compress(record(None, "", "warcinfo", "", 0, None, b"software: a Spark archive writer\r\n")))

    def add(self, *args) -> None:
        self.out.write(self.zip.compress(record(*args)))
        self.n += 1

    def close(self) -> tuple[str, int, int]:
        self.out.publish()
        return self.uri, self.n, self.out.size


def read_warc(uri: str) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and content of each record but warcinfo; the file is streamed, a record at a time."""
    store, path = open_store(uri)
    with store.open_input_stream(path, compression=None) as f:
        magic, n = struct.unpack("<II", f.read(8))
        if magic != SKIP_MAGIC:
            raise ValueError(f"{uri} has no leading dictionary frame")
        dictionary = f.read(n)
        make = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None)
        held, unzip, out = f.read(1 << 20), make.decompressobj(), []
        while held:
            out.append(unzip.decompress(held))
            held = unzip.unused_data if unzip.eof else b""
            if unzip.eof:
                got = parse(b"".join(out))
                if got[0]["WARC-Type"] != "warcinfo":
                    yield got
                unzip, out = make.decompressobj(), []
            held = held or f.read(1 << 20)


def write_archives(pages: DataFrame, folder: str, payload: str = "html", url: str = "url", file_bytes: int = FILE_BYTES) -> DataFrame:
    """Writes the archives; returns their manifest (uri, n_records, bytes), one row per file."""
    spark = pages.sparkSession
    dictionary = spark.sparkContext.broadcast(train_dictionary(pages, payload))
    body = pages.select(column(pages, "page_id", "long").alias("page_id"), F.coalesce(column(pages, url, "string"), F.lit("")).alias("url"), F.coalesce(column(pages, payload, "string"), F.lit("")).alias("html"))
    body = body.withColumn("digest", F.sha2("html", 256))
    known = body.filter(F.octet_length("html") >= MIN_DEDUP)
    first = known.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).filter("n > 1").select("digest", "first")
    dealt = body.join(first, "digest", "left")

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, done, out = TaskContext.get().partitionId(), [], None
        for batch in batches:
            for digest, page, link, html, head in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if out is None:
                    out = WarcWriter(f"{folder}/part-{part:06d}-{len(done):04d}.warc.zst", dictionary.value)
                data = html.encode("utf-8", "surrogatepass")
                revisit = head is not None and head != page
                out.add(page, link, "revisit" if revisit else "response", digest, len(data), head, b"" if revisit else data)
                if out.out.size >= file_bytes:
                    done.append(out.close())
                    out = None
        if out is not None:
            done.append(out.close())
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int64()), pa.array([d[2] for d in done], pa.int64())], ["uri", "n_records", "bytes"])

    ordered = dealt.select("digest", "page_id", "url", "html", "first").sortWithinPartitions("digest", "page_id", "url")  # a task run again writes the same
    return cut(ordered.mapInArrow(write, "uri string, n_records long, bytes long"))


def read_archives(manifest: DataFrame, with_payload: bool = False) -> DataFrame:
    """page_id, url, record_type, refers_to, payload_bytes, payload_digest (and payload) of every record.

    The digest and size of a response are those of the bytes read; of a revisit, those that its header states.
    """
    dealt = manifest.select("uri").repartition(tasks(manifest.sparkSession, 12), "uri")

    def rows(batch: pa.RecordBatch) -> Iterator[tuple]:
        for uri in batch.column(0).to_pylist():
            for head, body in read_warc(uri):
                revisit = head["WARC-Type"] == "revisit"
                yield (int(head["X-Page-Id"]) if head["X-Page-Id"] else None, head["WARC-Target-URI"], head["WARC-Type"], int(head["X-Refers-To-Page"]) if revisit else None, int(head["X-Payload-Length"]) if revisit else len(body), head["WARC-Payload-Digest"].removeprefix("sha256:") if revisit else hashlib.sha256(body).hexdigest(), *([body] if with_payload else []))

    kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), *([pa.binary()] if with_payload else [])]
    names = ["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", *(["payload"] if with_payload else [])]

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held, size = [], 0
            for row in rows(batch):
                held.append(row)
                size += len(row[-1]) if with_payload else 1
                if len(held) >= 5000 or size > 1 << 25:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), kinds, strict=True)], names)
                    held, size = [], 0
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held, strict=True), kinds, strict=True)], names)

    return dealt.mapInArrow(read, "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string" + ", payload binary" * with_payload)


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    back = read_archives(write_archives(pages, new_folder(spark, "warc")))
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL = """
with p as (select page_id, coalesce(html, '') as html, sha256(coalesce(html, '')) as d from pages),
     f as (select d, min(page_id) as first from p where strlen(html) >= 100 group by d)
select p.page_id, strlen(p.html)::bigint as payload_bytes, p.d as payload_digest,
       case when f.first is null or f.first = p.page_id then 'response' else 'revisit' end as record_type,
       case when f.first <> p.page_id then f.first end as refers_to
from p left join f on p.d = f.d
"""
