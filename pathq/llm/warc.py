"""WARC archives with a compression dictionary in each file.

Every file starts with a skippable frame that holds a Zstandard dictionary, trained on the file's own first records;
after it comes one frame per record, each compressed alone with that dictionary, so that any record can be read
by its offset. Of records with equal payloads of at least ``least_bytes``, the one with the largest id is a response
and the others are revisits without payload that refer to it.

Files are written by tasks into the shared folder under names of their own; only those that the committed manifest
lists count, so a task that runs twice leaves no double records. A file is closed at about ``file_bytes``.

Edge cases: null and empty payloads are records of length 0. A null page_id is written as ``null`` and read back as null;
it never becomes the response of a group that has an id. Rows that repeat an id and payload are all responses if that
id is their group's largest. A null url leaves the target header out. Files too small to train on have no dictionary
frame. An empty table gives no files. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.llm.common import Workspace, filesystem

DICTIONARY_MAGIC = (0x184D2A5D).to_bytes(4, "little")  # fixed value of the format
SCHEME = "urn:x-page:"
MANIFEST = "file string, n_records long, n_bytes long"
READ = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, payload string"


def _clean(value: str) -> str:
    return "".join(c if " " < c < "\x7f" else "".join(f"%{b:02X}" for b in c.encode()) for c in value)


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, digest: str, date: str) -> bytes:
    """One WARC/1.1 record: an HTTP response, or a revisit with its headers only."""
    name = "null" if page_id is None else str(page_id)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <{SCHEME}{name}>", f"WARC-Date: {date}"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {_clean(url)}")
    if refers_to is not None:
        lines += [f"WARC-Refers-To: <{SCHEME}{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += [f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(data: bytes) -> dict | None:
    """What a record says, with the payload's length and digest computed anew for responses; None for other records."""
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = {k.lower(): v.strip() for k, _, v in (line.partition(":") for line in head.decode("utf-8").split("\r\n")[1:])}
    if fields.get("warc-type") not in ("response", "revisit"):
        return None
    block = rest[: int(fields["content-length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    said = next(int(x.split(b":")[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length"))
    number = lambda x: None if x in ("", "null") else int(x)
    told = fields["warc-payload-digest"].partition(":")[2]
    if fields["warc-type"] == "response":
        if len(payload) != said or hashlib.sha1(payload).hexdigest() != told:
            raise ValueError(f"record {fields['warc-record-id']} is damaged")
    return {
        "page_id": number(fields["warc-record-id"].removeprefix(f"<{SCHEME}").removesuffix(">")),
        "payload_bytes": said,
        "payload_digest": told,
        "record_type": fields["warc-type"],
        "refers_to": number(fields.get("warc-refers-to", "").removeprefix(f"<{SCHEME}").removesuffix(">")),
        "url": fields.get("warc-target-uri"),
        "payload": payload,
    }


class Writer:
    """One file: records wait until there are enough to train on, then the dictionary frame and all frames follow."""

    def __init__(self, stream, level: int, dictionary_bytes: int, train_bytes: int):
        self.stream, self.level, self.dictionary_bytes, self.train_bytes = stream, level, dictionary_bytes, train_bytes
        self.waiting: list[bytes] = []
        self.waiting_bytes = self.n_bytes = self.n_records = 0
        self.compressor: zstandard.ZstdCompressor | None = None

    def _put(self, data: bytes) -> None:
        self.stream.write(data)
        self.n_bytes += len(data)

    def _begin(self) -> None:
        words = None
        if len(self.waiting) >= 16:
            try:
                words = zstandard.train_dictionary(min(self.dictionary_bytes, max(1024, self.waiting_bytes // 8)), [x[:65536] for x in self.waiting])
            except zstandard.ZstdError:  # samples that have nothing in common
                words = None
        if words is not None:
            body = words.as_bytes()
            self._put(DICTIONARY_MAGIC + len(body).to_bytes(4, "little") + body)
            self.compressor = zstandard.ZstdCompressor(level=self.level, dict_data=words)
        else:
            self.compressor = zstandard.ZstdCompressor(level=self.level)
        for data in self.waiting:
            self._put(self.compressor.compress(data))
        self.waiting = []

    def add(self, data: bytes) -> None:
        self.n_records += 1
        if self.compressor is None:
            self.waiting.append(data)
            self.waiting_bytes += len(data)
            if self.waiting_bytes >= self.train_bytes:
                self._begin()
        else:
            self._put(self.compressor.compress(data))

    def close(self) -> None:
        if self.compressor is None:
            self._begin()
        self.stream.close()


def frames(stream, chunk: int = 1 << 15) -> Iterator[bytes]:
    """Records of one file, in order, holding one record and one chunk at a time."""
    held = stream.read(8)
    words = None
    if held[:4] == DICTIONARY_MAGIC:
        words, held = zstandard.ZstdCompressionDict(stream.read(int.from_bytes(held[4:], "little"))), b""
    reader = zstandard.ZstdDecompressor(dict_data=words)
    while True:
        if not held and not (held := stream.read(chunk)):
            return
        one, parts = reader.decompressobj(), []
        while True:
            parts.append(one.decompress(held))
            if one.eof:
                held = one.unused_data
                break
            if not (held := stream.read(chunk)):
                raise ValueError("the file ends inside a record")
        yield b"".join(parts)


def _write(folder: str, date: str, level: int, dictionary_bytes: int, train_bytes: int, file_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = filesystem(folder)
        fs.create_dir(base, recursive=True)
        out, path, done = None, "", []
        info = b"WARC/1.1\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <urn:uuid:%s>\r\nWARC-Date: %s\r\nContent-Type: application/warc-fields\r\nContent-Length: 0\r\n\r\n\r\n\r\n"
        for batch in batches:
            for page_id, url, payload, refers, digest in zip(*(batch[c] for c in ("page_id", "url", "payload", "refers_to", "digest")), strict=True):
                if out is None:
                    name = uuid.uuid4()
                    path = f"{base}/pages-{name.hex}.warc.zst"
                    out = Writer(fs.open_output_stream(path), level, dictionary_bytes, train_bytes)
                    out.add(info % (str(name).encode(), date.encode()))
                out.add(record(page_id.as_py(), url.as_py(), payload.as_py(), refers.as_py(), digest.as_py(), date))
                if out.n_bytes + out.waiting_bytes * (out.compressor is None) >= file_bytes:
                    out.close()
                    done.append((path, out.n_records, out.n_bytes))
                    out = None
        if out is not None:
            out.close()
            done.append((path, out.n_records, out.n_bytes))
        if done:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*done, strict=True)], names=["file", "n_records", "n_bytes"])

    return run


def _read(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = filesystem(folder)
        for batch in batches:
            for path in batch["file"]:
                rows, size = [], 0
                with fs.open_input_stream(path.as_py()) as stream:
                    for data in frames(stream):
                        if (said := parse_record(data)) is None:
                            continue
                        rows.append(said)
                        size += len(data)
                        if len(rows) >= 1000 or size > 1 << 23:
                            yield _batch(rows)
                            rows, size = [], 0
                if rows:
                    yield _batch(rows)

    return run


def _batch(rows: list[dict]) -> pa.RecordBatch:
    kinds = {"page_id": pa.int64(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "record_type": pa.string(), "refers_to": pa.int64(), "url": pa.string()}
    columns = [pa.array([r[c] for r in rows], k) for c, k in kinds.items()]
    return pa.RecordBatch.from_arrays([*columns, pa.array([r["payload"].decode("utf-8") for r in rows], pa.string())], names=[*kinds, "payload"])


def write(pages: DataFrame, folder: str | None = None, least_bytes: int = 1000, date: str = "2000-01-01T00:00:00Z", level: int = 3, dictionary_bytes: int = 112_640, train_bytes: int = 4 << 20, file_bytes: int = 128 << 20) -> tuple[DataFrame, str]:
    """Archives ``pages`` (page_id, url, html). Returns the manifest (file, n_records, n_bytes) and the folder."""
    work = Workspace(pages.sparkSession, "warc")
    folder = folder or work.path("archives")
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload")).withColumn("digest", F.sha1("payload"))
    seen = work.table(rows.filter(F.octet_length("payload") >= least_bytes).select("page_id", "digest"), "digests")
    groups = work.table(seen.groupBy("digest").agg(F.max("page_id").alias("response"), F.count(F.lit(1)).alias("n")).filter("n > 1 and response is not null").select("digest", "response"), "groups")
    repeats = work.table(seen.join(groups, "digest").filter(~F.col("page_id").eqNullSafe(F.col("response"))).distinct(), "repeats")
    repeats = repeats.select(F.col("page_id").alias("__p"), F.col("digest").alias("__d"), F.col("response").alias("refers_to"))
    # null ids have one key in common; the digest spreads them
    full = rows.join(repeats, F.col("page_id").eqNullSafe(F.col("__p")) & (F.col("digest") == F.col("__d")), "left")
    written = full.select("page_id", "url", "payload", "refers_to", "digest").mapInArrow(_write(folder, date, level, dictionary_bytes, train_bytes, file_bytes), MANIFEST)
    return work.table(written, "manifest"), folder


def read(manifest: DataFrame, folder: str) -> DataFrame:
    """Records of the manifest's files: page_id, payload_bytes, payload_digest, record_type, refers_to, url, payload."""
    n = max(1, manifest.count())  # a file each
    return manifest.select("file").repartition(n).mapInArrow(_read(folder), READ)


def op7_warc(spark, sf_dir: str) -> DataFrame:
    manifest, folder = write(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"))
    return read(manifest, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
