"""WARC archives: a writer of one gzip member per record and a sequential reader.

The reader decompresses incrementally, frames each record by its content length
and verifies block and payload digests as the bytes pass. Files are opened by
URI through ``pyarrow.fs``; on a cluster the folder must be one that all
executors reach.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from typing import BinaryIO

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from modelsort.plans.durable import materialize, new_folder

#: The table has no fetch times; every record carries this date.
DATE = "1970-01-01T00:00:00Z"
#: Payloads of at least so many bytes are stored once.
REVISIT_BYTES = 0
#: Places that the rows of one payload are dealt over when they learn which of them answers.
SALTS = 256
LEVEL = 6
CHUNK = 1 << 16
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


class WarcError(ValueError):
    """An archive that breaks its framing or whose bytes don't have its digests."""


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(page_id: int | None, url: str | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id}' if page_id is not None else f'page {url}')}>"


def _header_value(text: str) -> str:
    return text.replace("%", "%25").replace("\r", "%0D").replace("\n", "%0A") if set(text) & {"\r", "\n"} else text


def write_record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, level: int = LEVEL) -> bytes:
    """One record as a gzip member: a response, or a revisit of page ``refers_to``."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    fields = [
        ("WARC-Type", "response" if refers_to is None else "revisit"),
        ("WARC-Record-ID", record_id(page_id, url)),
        ("WARC-Date", DATE),
        ("WARC-Target-URI", _header_value(url or "about:blank")),
        ("Content-Type", "application/http;msgtype=response"),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("WARC-Block-Digest", f"sha1:{base32_sha1(block)}"),
    ]
    if page_id is not None:
        fields.append(("Page-ID", str(page_id)))
    if refers_to is not None:
        fields += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to, None)), ("Refers-To-Page-ID", str(refers_to))]
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields) + f"Content-Length: {len(block)}\r\n\r\n"
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress(head.encode() + block + b"\r\n\r\n") + packer.flush()


@dataclass
class Record:
    """A record that was read: its header fields, its payload's size and digest, and the payload if kept."""

    fields: dict[str, str]
    payload_bytes: int
    payload_digest: str
    payload: bytes | None


class _Member:
    """Bytes of one gzip member, decompressed as they are asked for."""

    def __init__(self, source: BinaryIO, start: bytes):
        self.source, self.packed, self.plain = source, start, bytearray()
        self.unzip = zlib.decompressobj(31)

    def more(self) -> bool:
        """Decompress up to one chunk more; false at the member's end."""
        while not self.unzip.eof:
            self.packed = self.packed or self.source.read(CHUNK)
            if not self.packed:
                raise WarcError("the archive ends within a member")
            try:
                got = self.unzip.decompress(self.packed, CHUNK)
            except zlib.error as bad:
                raise WarcError(f"broken member: {bad}") from bad
            self.packed = self.unzip.unconsumed_tail
            if got:
                self.plain += got
                return True
        return False

    def until(self, mark: bytes, most: int = 1 << 20) -> bytes:
        at = 0
        while (found := self.plain.find(mark, max(0, at - len(mark)))) < 0:
            at = len(self.plain)
            if at > most or not self.more():
                raise WarcError("a header has no end")
        out = bytes(self.plain[:found])
        del self.plain[: found + len(mark)]
        return out

    def exactly(self, size: int) -> Iterator[bytes]:
        while size:
            if not self.plain and not self.more():
                raise WarcError("a record is shorter than its content length")
            part = bytes(self.plain[:size])
            del self.plain[: len(part)]
            size -= len(part)
            yield part

    def end(self) -> bytes:
        """Check that only the record's end is left; give the bytes of the next member."""
        while self.more():
            pass
        if self.plain != b"\r\n\r\n":
            raise WarcError("a member doesn't end with its record")
        return self.unzip.unused_data


def _fields(head: bytes) -> dict[str, str]:
    return {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in head.decode("utf-8").split("\r\n")[1:])}


def read_records(source: BinaryIO, keep_payload: bool = False) -> Iterator[Record]:
    """Records of an archive in order; raises ``WarcError`` at the first that doesn't verify."""
    rest = b""
    while rest or (rest := source.read(CHUNK)):
        member = _Member(source, rest)
        head = member.until(b"\r\n\r\n")
        if not head.startswith(b"WARC/"):
            raise WarcError("a member doesn't begin with a record")
        fields = _fields(head)
        block, payload = hashlib.sha1(), hashlib.sha1()
        http, size, kept = bytearray(), None, bytearray()
        for part in member.exactly(int(fields["content-length"])):
            block.update(part)
            if size is None:
                http += part
                if (at := http.find(b"\r\n\r\n")) >= 0:
                    part, size = bytes(http[at + 4 :]), 0
                    del http[at:]
                else:
                    continue
            size += len(part)
            payload.update(part)
            if keep_payload:
                kept += part
        rest = member.end()
        encode = lambda h: base64.b32encode(h.digest()).decode()
        if fields.get("warc-block-digest", "").removeprefix("sha1:") != encode(block):
            raise WarcError(f"block digest of {fields.get('warc-record-id')}")
        stated, declared = fields.get("warc-payload-digest", "").removeprefix("sha1:"), int(_fields(bytes(http))["content-length"])
        if fields["warc-type"] == "revisit":
            yield Record(fields, declared, stated, None)
        elif stated != encode(payload) or declared != size:
            raise WarcError(f"payload digest of {fields.get('warc-record-id')}")
        else:
            yield Record(fields, size, stated, bytes(kept) if keep_payload else None)


def _open(uri: str, mode: str):
    system, path = pafs.FileSystem.from_uri(uri if ":" in uri else f"file://{uri}")
    if mode == "w":
        system.create_dir(path.rsplit("/", 1)[0], recursive=True)
        return system.open_output_stream(path)
    return system.open_input_stream(path)


def with_revisits(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """Columns ``page_id, url, payload, sha1, refers_to``; ``refers_to`` is set for revisits only.

    Of equal payloads the one of largest page_id answers; rows that repeat that
    id and payload answer too. A group without any id has no revisits. Payloads
    move once, a group of any size dealt over ``SALTS`` places; what they meet
    there is at most that many rows of a digest.
    """
    salt = F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.encode(F.coalesce(F.col("html"), F.lit("")), "utf-8").alias("payload")).withColumn("sha1", F.sha1("payload")).withColumn("salt", salt)
    dealt = rows.where(F.length("payload") >= least).groupBy("sha1", "salt").agg(F.max("page_id").alias("largest"), F.count("*").alias("n"))
    repeated = dealt.groupBy("sha1").agg(F.max("largest").alias("first"), F.sum("n").alias("n")).where("n > 1 and first is not null").select("sha1", "first")
    places = dealt.select("sha1", "salt").join(repeated, "sha1")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    return rows.join(places, ["sha1", "salt"], "left").select("page_id", "url", "payload", "sha1", refers.alias("refers_to"))


def write_archives(pages: DataFrame, folder: str | None = None, least: int = REVISIT_BYTES, level: int = LEVEL) -> DataFrame:
    """Write archives and return their manifest ``path, records, bytes``.

    Each task writes one file under a name of its own attempt, and only the
    attempts that succeed are in the manifest, so lost or repeated tasks do no
    harm. Null payloads are empty. An empty table writes no archive.
    """
    folder = folder or new_folder(pages.sparkSession, "warc")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        path, out, records, size = f"{folder}/{uuid.uuid4().hex}.warc.gz", None, 0, 0
        for batch in batches:
            columns = [batch.column(c) for c in ("page_id", "url", "payload", "sha1", "refers_to")]
            for page_id, url, payload, sha1, refers_to in zip(*columns, strict=True):
                out = out or _open(path, "w")
                digest = base64.b32encode(bytes.fromhex(sha1.as_py())).decode()
                member = write_record(page_id.as_py(), url.as_py(), payload.as_py(), digest, refers_to.as_py(), level)
                out.write(member)
                records, size = records + 1, size + len(member)
        if out:
            out.close()
            yield pa.RecordBatch.from_pylist([{"path": path, "records": records, "bytes": size}])

    return materialize(with_revisits(pages, least).mapInArrow(run, "path string, records long, bytes long"), "warc-manifest")


def read_archives(manifest: DataFrame, keep_payload: bool = False) -> DataFrame:
    """A row per record of the archives in ``path``, each read in order and verified."""
    ddl = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])

    def rows(uri: str) -> Iterator[dict]:
        with _open(uri, "r") as source:
            for r in read_records(source, keep_payload):
                number = lambda k, f=r.fields: int(f[k]) if k in f else None
                yield {"page_id": number("page-id"), "url": r.fields.get("warc-target-uri"), "payload_bytes": r.payload_bytes, "payload_digest": r.payload_digest, "record_type": r.fields["warc-type"], "refers_to": number("refers-to-page-id"), "payload": r.payload}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri in batch.column("path").to_pylist():
                ready, held = [], 0
                for row in rows(uri):
                    ready.append(row)
                    held += 200 + len(row["payload"] or b"")
                    if held > 4 << 20:
                        yield pa.RecordBatch.from_pylist(ready, schema)
                        ready, held = [], 0
                if ready:
                    yield pa.RecordBatch.from_pylist(ready, schema)

    files = manifest.count()
    return manifest.select("path").repartition(max(1, files), "path").mapInArrow(run, ddl)


def check_revisits(records: DataFrame) -> DataFrame:
    """The same records; ``WarcError`` if a revisit states a digest or size that no response it refers to has.

    Revisits are combined by what they state before they meet the responses, so
    a payload of many revisits is one row. Records must be stable when read again.
    """
    stated = records.where("record_type = 'revisit'").select("refers_to", "payload_digest", "payload_bytes").distinct()
    there = records.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), "payload_digest", "payload_bytes")
    if wrong := stated.join(there, ["refers_to", "payload_digest", "payload_bytes"], "left_anti").head():
        raise WarcError(f"no response of page {wrong['refers_to']} has payload digest {wrong['payload_digest']} and {wrong['payload_bytes']} bytes")
    return records
