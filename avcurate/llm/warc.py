"""WARC archives in Zstandard: one frame a record, the dictionary in a leading skippable frame.

An archive is a row (archive_id, warc binary) of a table in the shared folder, so that any
executor can write and read it through Spark; ``read_archives`` takes such rows from any source,
for instance Spark's ``binaryFile``. The writer keeps an archive below ``archive_bytes`` (one
record may exceed it). The dictionary is trained on at most ``dict_samples`` pages, chosen by
hashes of their ids, and at most ``sample_bytes`` of each; where training has too little to
go by, the samples themselves serve as a raw dictionary.

Of records with equal payloads of at least ``revisit_bytes``, the one with the smallest page_id is
the response; the others are revisits, which keep headers alone.

Edge cases: null html is an empty payload; null url has no target header; a null page_id is
written as an empty id and read back as null (as a referred page it counts last); repeated rows of
one page_id: each revisits that id, but for one row, chosen by url; an empty table gives no
archives; extra columns are ignored. The reader raises ValueError on a frame, header, length or
digest that doesn't hold; ``checked`` also on a revisit whose response isn't there.
"""

from __future__ import annotations

import hashlib
import re
import struct
from collections.abc import Iterator

import pyarrow as pa
import zstandard as zstd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from avcurate.llm.common import parts_of, stage

#: Fixed values of the format: the skippable frame that may hold a dictionary, a dictionary's and a frame's first bytes.
DICT_FRAME, DICT_MAGIC, FRAME_MAGIC = 0x184D2A5D, b"\x37\xa4\x30\xec", b"\x28\xb5\x2f\xfd"
HTTP_HEAD = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
READ_SCHEMA = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string"


# --- bytes of one record -------------------------------------------------------------------------


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, kind: str, refers_to: int | None) -> bytes:
    block = HTTP_HEAD + payload if kind == "response" else b""
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", "WARC-Date: 2024-01-01T00:00:00Z"]
    if url is not None:
        head.append("WARC-Target-URI: " + re.sub(r"[\x00-\x20]", lambda m: f"%{ord(m[0]):02X}", url))
    head += [f"WARC-Payload-Digest: sha256:{digest}", f"WARC-Payload-Length: {len(payload)}"]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    else:
        head.append("Content-Type: application/http; msgtype=response")
    head.append(f"Content-Length: {len(block)}")
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(raw: bytes, with_payload: bool = False) -> tuple:
    head, sep, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    if not sep or not re.fullmatch(r"WARC/1\.\d", lines[0]):
        raise ValueError("no WARC header")
    fields = {}
    for line in lines[1:]:
        name, colon, value = line.partition(":")
        if not colon:
            raise ValueError(f"bad header line {line[:60]!r}")
        fields[name.strip().lower()] = value.strip()
    for need in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if need not in fields:
            raise ValueError(f"header {need} is missing")
    n = int(fields["content-length"])
    if len(rest) != n + 4 or rest[n:] != b"\r\n\r\n":
        raise ValueError(f"content length {n}, but the record holds {len(rest) - 4}")
    kind, own = fields["warc-type"], _page(fields["warc-record-id"])
    digest = fields.get("warc-payload-digest", "").removeprefix("sha256:")
    if kind == "response":
        _, sep, payload = rest[:n].partition(b"\r\n\r\n")
        if not sep:
            raise ValueError("no HTTP header in a response")
        size, found = len(payload), hashlib.sha256(payload).hexdigest()
        if digest and found != digest:
            raise ValueError("payload digest doesn't hold")
        refers = None
    elif kind == "revisit":
        payload, size, found, refers = b"", int(fields["warc-payload-length"]), digest, _page(fields["warc-refers-to"])
    else:
        raise ValueError(f"unexpected record type {kind}")
    return (own, size, found, kind, refers, fields.get("warc-target-uri")) + ((payload,) if with_payload else ())


def _page(urn: str) -> int | None:
    m = re.fullmatch(r"<urn:page:(-?\d*)>", urn)
    if not m:
        raise ValueError(f"bad record id {urn[:60]!r}")
    return int(m[1]) if m[1] else None


# --- bytes of an archive -------------------------------------------------------------------------


def dictionary_frame(data: bytes) -> bytes:
    return struct.pack("<II", DICT_FRAME, len(data)) + data


def read_dictionary(archive: memoryview) -> tuple[bytes | None, int]:
    """The dictionary of the leading skippable frame, if there is one, and where the records begin."""
    if len(archive) < 8 or struct.unpack_from("<I", archive)[0] != DICT_FRAME:
        return None, 0
    size = struct.unpack_from("<I", archive, 4)[0]
    if 8 + size > len(archive):
        raise ValueError("the dictionary's frame is cut short")
    data = bytes(archive[8 : 8 + size])
    if data[:4] == FRAME_MAGIC:  # it may itself be compressed
        data = zstd.ZstdDecompressor().decompress(data)
    return data, 8 + size


def frames(archive: bytes) -> Iterator[bytes]:
    """The records, one from each frame."""
    view = memoryview(archive)
    data, at = read_dictionary(view)
    d = zstd.ZstdDecompressor(dict_data=zstd.ZstdCompressionDict(data)) if data else zstd.ZstdDecompressor()
    while at < len(view):
        magic = struct.unpack_from("<I", view, at)[0] if at + 8 <= len(view) else 0
        if 0x184D2A50 <= magic <= 0x184D2A5F:  # other skippable frames
            at += 8 + struct.unpack_from("<I", view, at + 4)[0]
            continue
        if bytes(view[at : at + 4]) != FRAME_MAGIC:
            raise ValueError(f"no frame at byte {at}")
        o = d.decompressobj()
        out = [o.decompress(view[at : at + 65536])]
        end = min(at + 65536, len(view))
        while not o.eof and end < len(view):
            out.append(o.decompress(view[end : end + 65536]))
            end = min(end + 65536, len(view))
        if not o.eof:
            raise ValueError(f"the frame at byte {at} is cut short")
        at = end - len(o.unused_data)
        yield b"".join(out)


def train_dictionary(samples: list[bytes], size: int) -> bytes:
    try:
        return zstd.train_dictionary(size, samples).as_bytes()
    except zstd.ZstdError:
        raw = b"".join(samples)[-size:]
        return b"" if raw[:4] in (DICT_MAGIC, FRAME_MAGIC) else raw


# --- tables ----------------------------------------------------------------------------------------


def dictionary_for(pages: DataFrame, dict_samples: int = 200, sample_bytes: int = 8192, dict_bytes: int = 32768) -> bytes:
    n = pages.count()
    near = F.pmod(F.xxhash64("page_id"), F.lit(1 << 30)) <= F.lit(min(1 << 30, (2 * dict_samples << 30) // max(1, n)))
    rows = (
        pages.where(near & F.col("html").isNotNull())
        .select(F.xxhash64("page_id").alias("h"), F.substring("html", 1, sample_bytes).alias("s"))
        .orderBy("h", "s").limit(dict_samples).collect()
    )
    return train_dictionary([r.s.encode()[:sample_bytes] for r in rows if r.s], dict_bytes)


def with_record_types(pages: DataFrame, revisit_bytes: int = 100) -> DataFrame:
    """page_id, url, html, payload_digest, record_type, refers_to.

    The copies of a payload are found by partial minima of narrow rows; only digests that repeat
    are joined back, and that join may be split where one payload holds many rows.
    """
    html = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    rows = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"), F.sha2(html, 256).alias("payload_digest"), F.octet_length(F.coalesce("html", F.lit(""))).alias("n_bytes"))
    first = (
        rows.where(F.col("n_bytes") >= revisit_bytes)
        .groupBy("payload_digest")
        .agg(F.count("*").alias("n"), F.min(F.struct(F.col("page_id").isNull().alias("none"), "page_id", F.col("url"))).alias("f"))
        .where("n > 1").select("payload_digest", F.col("f.page_id").alias("first_id"), F.col("f.url").alias("first_url"))
    )
    first = stage(first, "warc-first")
    joined = rows.join(first.withColumn("repeats", F.lit(True)), "payload_digest", "left")
    is_first = F.col("repeats").isNull() | (F.col("page_id").eqNullSafe(F.col("first_id")) & F.col("url").eqNullSafe(F.col("first_url")))
    return joined.select(
        "page_id", "url", "html", "payload_digest",
        F.when(is_first, F.lit("response")).otherwise(F.lit("revisit")).alias("record_type"),
        F.when(~is_first, F.col("first_id")).alias("refers_to"),
    )


def write_archives(typed: DataFrame, dictionary: bytes, archive_bytes: int = 16 << 20, level: int = 3) -> DataFrame:
    """(archive_id, records, warc): written per task while rows stream by, so no shuffle is needed."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = zstd.ZstdCompressor(level=level, dict_data=zstd.ZstdCompressionDict(dictionary), write_checksum=True) if dictionary else zstd.ZstdCompressor(level=level, write_checksum=True)
        part, serial = TaskContext.get().partitionId(), 0
        out, size = [], 0

        def flush() -> pa.RecordBatch:
            nonlocal out, size, serial
            done = pa.RecordBatch.from_pydict({"archive_id": [(part << 24) + serial], "records": [len(out)], "warc": [dictionary_frame(dictionary) + b"".join(out)]})
            out, size, serial = [], 0, serial + 1
            return done

        for b in batches:
            for some in parts_of(b, "html"):
                for pid, url, html, digest, kind, ref in zip(*(some.column(c).to_pylist() for c in ("page_id", "url", "html", "payload_digest", "record_type", "refers_to"))):
                    raw = record(pid, url, html.encode(), digest, kind, "" if ref is None else ref)
                    out.append(f := c.compress(raw))
                    size += len(f)
                    if size >= archive_bytes:
                        yield flush()
        if out:
            yield flush()

    return typed.mapInArrow(write, "archive_id long, records long, warc binary")


def read_archives(archives: DataFrame, column: str = "warc", payloads: bool = False) -> DataFrame:
    """One row for each record: page_id, payload_bytes, payload_digest, record_type, refers_to, url (and payload)."""
    ddl = READ_SCHEMA + ", payload binary" * payloads
    schema = to_arrow_schema(StructType.fromDDL(ddl))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def send(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*rows), schema.types)], schema=schema)

        for b in batches:
            for raw in b.column(column):
                rows, held = [], 0
                for f in frames(raw.as_py()):
                    rows.append(parse_record(f, payloads))
                    held += len(f)
                    if len(rows) >= 5000 or payloads and held > 8 << 20:
                        yield send(rows)
                        rows, held = [], 0
                if rows:
                    yield send(rows)

    return archives.select(column).mapInArrow(read, ddl)


def checked(records: DataFrame) -> DataFrame:
    """The records, staged, after each revisit has met the response that it names, with its length and digest; ValueError where one has not."""
    records = stage(records, "warc-records")
    of = ["payload_bytes", "payload_digest"]
    said = records.where("record_type = 'revisit'").select(F.col("refers_to").alias("page"), *of).distinct().alias("a")
    there = records.where("record_type = 'response'").select(F.col("page_id").alias("page"), *of).distinct().alias("b")
    same = F.col("a.page").eqNullSafe(F.col("b.page")) & (F.col("a.payload_bytes") == F.col("b.payload_bytes")) & (F.col("a.payload_digest") == F.col("b.payload_digest"))
    if not said.join(there, same, "left_anti").isEmpty():
        raise ValueError("a revisit names no response of its payload")
    return records


def archive_pages(pages: DataFrame, **dictionary_options) -> DataFrame:
    """Write the pages into staged archives; returns the table of archives."""
    return stage(write_archives(with_record_types(pages), dictionary_for(pages, **dictionary_options)), "warc")
