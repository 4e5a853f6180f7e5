"""WARC archives, each record a Zstandard frame of its own, all with one dictionary.

The dictionary is built from a bounded sample of the records and stored in a skippable frame in
front of each archive, so every archive can be read alone and any record by its offset. Equal
payloads are archived once: the smallest page id is the response, later ones are revisits
that name it.

Archives are written where all executors see them, under a temporary name that is then renamed, so
a task that runs twice leaves one whole file. A manifest row for each archive is written by
Spark; reading starts from the manifest.

Defined results: a null page has the empty payload; payloads under `revisit_bytes` are always responses;
rows that repeat the smallest page id are responses, too; a null page id is a response and never
referred to; an empty table gives no archive and no rows.
"""

from __future__ import annotations

import os
import struct
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_sample, materialise, scratch_dir, table

# Fixed values of the file format.
SKIPPABLE = 0x184D2A5D
FRAME = b"\x28\xb5\x2f\xfd"
DATE = "1970-01-01T00:00:00Z"


@dataclass(frozen=True)
class WarcConfig:
    """sample, sample_bytes: records, and bytes of each, that the dictionary is built from;
    dictionary: its size; level: of compression; revisit_bytes: least payload of a revisit; hot: so many groups of copies,
    the largest, are looked up by broadcast (some 100 bytes each); any other has a share of 1 / hot of the rows at
    most, and meets its head in one task; archive_bytes: of payload in an archive, about."""

    sample: int = 1000
    sample_bytes: int = 16384
    dictionary: int = 65536
    level: int = 3
    revisit_bytes: int = 100
    hot: int = 5000
    archive_bytes: int = 64 << 20


def build_dictionary(pages: DataFrame, cfg: WarcConfig, html: str = "html", key: str = "page_id") -> bytes:
    """From at most cfg.sample records, by a hash of the id; b'' where they are too few."""
    rows = bounded_sample(pages.where(F.col(html).isNotNull()), F.col(key), cfg.sample).select(F.encode(F.substring(html, 1, cfg.sample_bytes), "utf-8").alias("b")).collect()
    parts = [bytes(r["b"]) for r in rows if r["b"]]
    try:
        return zstandard.train_dictionary(cfg.dictionary, parts).as_bytes() if len(parts) >= 8 else b""
    except zstandard.ZstdError:
        return b""  # too little text to learn from


def plan(pages: DataFrame, cfg: WarcConfig, key: str = "page_id", html: str = "html", url: str = "url") -> DataFrame:
    """(page_id, url, payload, digest, refers_to): refers_to is null for a response."""
    rows = pages.select(F.col(key).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), F.encode(F.coalesce(F.col(html), F.lit("")), "utf-8").alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    long = F.length("payload") >= cfg.revisit_bytes
    heads = rows.where(long).groupBy("digest").agg(F.min("page_id").alias("head"), F.count(F.lit(1)).alias("copies")).where("copies > 1")
    heads = materialise(heads)
    largest = materialise(heads.orderBy(F.desc("copies"), "digest").limit(cfg.hot).select("digest", "head"))
    hot = largest.select(F.col("digest").alias("hot_digest"), F.col("head").alias("hot_head"))
    rows = rows.join(F.broadcast(hot), F.col("digest") == F.col("hot_digest"), "left")
    # Rows of hot groups have their answer; a key of their own keeps them out of one task.
    spread = F.when(F.col("hot_head").isNotNull(), F.concat(F.lit("-"), F.xxhash64("page_id").cast("string"))).otherwise(F.col("digest"))
    rows = rows.withColumn("cold_digest", spread).join(heads.join(largest, "digest", "left_anti").select(F.col("digest").alias("cold_digest"), F.col("head").alias("cold_head")), "cold_digest", "left")
    head = F.coalesce("hot_head", "cold_head")
    return rows.select("page_id", "url", "payload", "digest", F.when(F.col("page_id") > head, head).alias("refers_to"))


def record_id(page_id: int | None, referred: bool) -> str:
    """Pages that others refer to are known by their id; any other record has an id of its own, as ids may repeat or lack."""
    return f"<urn:uuid:{uuid.UUID(int=page_id & ((1 << 128) - 1)) if referred and page_id is not None else uuid.uuid4()}>"


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC record; a revisit has no payload, but its size and digest."""
    kind = "response" if refers_to is None else "revisit"
    body = payload if refers_to is None else b""
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page_id, refers_to is None)}", f"WARC-Date: {DATE}", f"WARC-Target-URI: {(url or '').replace(chr(13), '%0D').replace(chr(10), '%0A')}", f"WARC-Payload-Digest: sha256:{digest}"]
    if page_id is not None:
        head.append(f"X-Page-ID: {page_id}")
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers_to, True)}", f"X-Refers-To-Page-ID: {refers_to}", f"X-Payload-Length: {len(payload)}"]
    head += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = raw.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    n = int(fields["Content-Length"])
    if rest[n:] != b"\r\n\r\n":
        raise ValueError("a record does not end where its header says")
    return fields, rest[:n]


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (pafs.LocalFileSystem(), path)


class ArchiveWriter:
    """One archive: the dictionary's frame, then a frame for each record."""

    def __init__(self, folder: str, dictionary: bytes, level: int) -> None:
        self.fs, base = _open(folder)
        self.fs.create_dir(base, recursive=True)
        self.name = f"{uuid.uuid4().hex}.warc.zst"
        self.path, self.temp = f"{base}/{self.name}", f"{base}/.{self.name}.tmp"
        self.out = self.fs.open_output_stream(self.temp, compression=None)
        self.out.write(struct.pack("<II", SKIPPABLE, len(dictionary)) + dictionary)
        kind = {"dict_data": zstandard.ZstdCompressionDict(dictionary)} if dictionary else {}
        self.pack = zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True, **kind)
        self.records = self.raw = 0

    def write(self, raw: bytes) -> None:
        self.out.write(self.pack.compress(raw))
        self.records += 1
        self.raw += len(raw)

    def close(self) -> tuple[str, int, int]:
        self.out.close()
        self.fs.move(self.temp, self.path)
        return self.name, self.records, self.raw

    def drop(self) -> None:
        self.out.close()
        self.fs.delete_file(self.temp)


def read_archive(folder: str, name: str) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header and content of each record, by the dictionary in the archive itself."""
    fs, base = _open(folder)
    with fs.open_input_stream(f"{base}/{name}", compression=None) as f:
        magic, size = struct.unpack("<II", f.read(8))
        if magic != SKIPPABLE:
            raise ValueError("the archive does not start with a dictionary frame")
        dictionary = f.read(size)
        kind = {"dict_data": zstandard.ZstdCompressionDict(dictionary)} if dictionary else {}
        one = zstandard.ZstdDecompressor(**kind)
        rest = b""
        frame = one.decompressobj()
        whole: list[bytes] = []
        while True:
            block = rest or f.read(1 << 20)
            rest = b""
            if not block:
                if whole:
                    raise ValueError("the archive ends within a record")
                return
            whole.append(frame.decompress(block))
            if frame.eof:
                rest = frame.unused_data
                yield parse_record(b"".join(whole))
                frame, whole = one.decompressobj(), []


def write(pages: DataFrame, folder: str, cfg: WarcConfig = WarcConfig()) -> DataFrame:
    """Archives all pages in `folder`, which all executors see; returns the manifest
    (name, records, bytes), itself written to the shared scratch folder."""
    dictionary = pages.sparkSession.sparkContext.broadcast(build_dictionary(pages, cfg))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: ArchiveWriter | None = None
        done = []
        try:
            for b in batches:
                for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    now = now or ArchiveWriter(folder, dictionary.value, cfg.level)
                    now.write(record(*row))
                    if now.raw >= cfg.archive_bytes:
                        done.append(now.close())
                        now = None
            if now:
                done.append(now.close())
                now = None
        finally:
            if now:
                now.drop()
        if done:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*done, strict=True)], ["name", "records", "bytes"])

    return materialise(plan(pages, cfg).mapInArrow(run, "name string, records long, bytes long"))


def read(spark: SparkSession, manifest: DataFrame, folder: str) -> DataFrame:
    """A row for each record of the archives in the manifest."""
    schema = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import hashlib

        names = schema.replace(",", "").split()[::2]
        for b in batches:
            for name in b["name"]:
                rows, held = [], 0
                for h, body in read_archive(folder, name):
                    first = h["WARC-Type"] == "response"
                    digest = hashlib.sha256(body).hexdigest() if first else h["WARC-Payload-Digest"].removeprefix("sha256:")
                    if first and digest != h["WARC-Payload-Digest"].removeprefix("sha256:"):
                        raise ValueError("a payload differs from its digest")
                    number = lambda k: int(h[k]) if k in h else None  # noqa: B023, E731
                    rows.append((number("X-Page-ID"), h["WARC-Target-URI"], len(body) if first else number("X-Payload-Length"), digest, h["WARC-Type"], number("X-Refers-To-Page-ID"), body))
                    held += len(body)
                    if held > 1 << 23 or len(rows) >= 5000:
                        yield _frame(rows, names)
                        rows, held = [], 0
                if rows:
                    yield _frame(rows, names)

    parts = max(1, min(manifest.count(), 4 * spark.sparkContext.defaultParallelism))
    return manifest.select("name").repartition(parts, "name").mapInPandas(run, schema)


def _frame(rows: list[tuple], names: list[str]) -> pd.DataFrame:
    out = pd.DataFrame(rows, columns=names)
    return out.astype({"page_id": "Int64", "refers_to": "Int64", "payload_bytes": "int64"})


def archive_folder(spark: SparkSession) -> str:
    path = scratch_dir(spark)
    return path if "://" in path or path.startswith("file:") else os.path.abspath(path)


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = archive_folder(spark)
    manifest = write(table(spark, sf_dir, "pages"), folder)
    return read(spark, manifest, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
