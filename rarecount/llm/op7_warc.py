"""Zstandard WARC archives: writer, reader and the page query.

Layout of an archive: a leading skippable frame holds the compression dictionary, then each record is one
Zstandard frame of its own. Each input partition writes its own archives, a new one whenever the last has
grown past ``roll_bytes``, under a name no other attempt uses; the table of names that finished tasks
report is the archive set, so a task that is run again leaves no doubles. Records of
equal payloads refer to the one with the smallest page id.

Defined results: a null html is an empty payload; a null or repeated page id is written like any other
(rows that share the smallest id of a payload are all responses); an empty table writes no archive
and reads back as no rows; further columns are ignored. Payloads are streamed record by record, after the first
``HELD_BYTES`` at most, which the dictionary is trained on.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import new_path, stored

#: Fixed values of the formats.
DICTIONARY_MAGIC = 0x184D2A5D
FRAME_MAGIC = 0xFD2FB528
ZSTD_DICTIONARY = b"\x37\xa4\x30\xec"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"

DICTIONARY_BYTES = 16_384
SAMPLE_RECORDS, SAMPLE_BYTES = 256, 4096
#: Records that wait for the dictionary take about so many bytes at most.
HELD_BYTES = 8 << 20
ROLL_BYTES = 64 << 20


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page: int | None) -> str:
    return f"<urn:rarecount:page:{'none' if page is None else page}>"


def page_of(rid: str) -> int | None:
    tail = rid.strip("<>").rpartition(":")[2]
    return None if tail == "none" else int(tail)


def record(page: int | None, url: str | None, payload: bytes, first: int | None, is_revisit: bool) -> bytes:
    """One WARC record; a revisit keeps the HTTP head but not the payload."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head if is_revisit else head + payload
    url = "".join(c for c in url or "about:blank" if c not in "\r\n")
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if is_revisit else 'response'}",
        f"WARC-Record-ID: {record_id(page)}",
        f"WARC-Date: {DATE}",
        f"WARC-Target-URI: {url}",
        "Content-Type: application/http; msgtype=response",
        f"WARC-Payload-Digest: sha1:{digest(payload)}",
        f"WARC-Block-Digest: sha1:{digest(block)}",
        f"Content-Length: {len(block)}",
    ]
    if is_revisit:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(first)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class Malformed(ValueError):
    """A record or archive that breaks the format."""


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields (lower-case names) and block of exactly one record."""
    head, sep, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not sep or not lines[0].startswith("WARC/1."):
        raise Malformed("no WARC version line")
    fields = {}
    for line in lines[1:]:
        name, colon, value = line.partition(":")
        if not colon:
            raise Malformed(f"header line without a colon: {line[:80]!r}")
        fields[name.strip().lower()] = value.strip()
    for name in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if name not in fields:
            raise Malformed(f"no {name}")
    n = fields["content-length"]
    if not n.isdigit() or len(rest) != int(n) + 4 or not rest.endswith(b"\r\n\r\n"):
        raise Malformed("block length differs from Content-Length")
    block = rest[: int(n)]
    if (want := fields.get("warc-block-digest")) and want != f"sha1:{digest(block)}":
        raise Malformed("block digest differs")
    return fields, block


def summary(raw: bytes) -> tuple[int | None, int, str, str, int | None]:
    """(page id, payload bytes, payload digest, type, page referred to) of a checked record."""
    fields, block = parse(raw)
    http, sep, payload = block.partition(b"\r\n\r\n")
    sizes = [x.partition(b":")[2] for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")]
    kind, want = fields["warc-type"], fields.get("warc-payload-digest", "")
    if not sep or len(sizes) != 1:
        raise Malformed("no HTTP head")
    if kind == "response":
        if len(payload) != int(sizes[0]) or want != f"sha1:{digest(payload)}":
            raise Malformed("payload differs from its length or digest")
    elif kind != "revisit" or payload or "warc-refers-to" not in fields:
        raise Malformed(f"not a response nor a whole revisit: {kind}")
    first = page_of(fields["warc-refers-to"]) if kind == "revisit" else None
    return page_of(fields["warc-record-id"]), int(sizes[0]), want.removeprefix("sha1:"), kind, first


def trained(samples: list[bytes]) -> zstandard.ZstdCompressionDict | None:
    """A dictionary of the starts of the first records, or none where they are too few or too alike.

    Segment length and step are given, since searching for them takes hundreds of MB."""
    starts = list(dict.fromkeys(s[:SAMPLE_BYTES] for s in samples))
    if len(starts) < 16:
        return None
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, starts, k=256, d=8)
    except zstandard.ZstdError:
        return None


def put_archive(stream, records: Iterator[bytes], roll: int) -> int:
    """Write records until ``roll`` bytes are passed; returns how many."""
    first, held = [], 0
    for r in records:
        first.append(r)
        held += len(r)
        if len(first) >= SAMPLE_RECORDS or held > min(roll, HELD_BYTES):
            break
    book = trained(first)
    raw = book.as_bytes() if book else b""
    stream.write(struct.pack("<II", DICTIONARY_MAGIC, len(raw)) + raw)
    pack = zstandard.ZstdCompressor(level=3, dict_data=book, write_content_size=True, write_checksum=True)
    done, size = 0, 0
    for r in first:
        size += stream.write(pack.compress(r))
        done += 1
    while size < roll and (r := next(records, None)) is not None:
        size += stream.write(pack.compress(r))
        done += 1
    return done


def frames(stream, dictionary: zstandard.ZstdCompressionDict | None) -> Iterator[bytes]:
    """The content of one frame after the other."""
    waiting = b""
    while True:
        unpack = zstandard.ZstdDecompressor(dict_data=dictionary).decompressobj()
        out = []
        fresh = True
        while not unpack.eof:
            data = waiting or stream.read(1 << 20)
            waiting = b""
            if not data:
                if fresh:
                    return
                raise Malformed("the archive ends within a frame")
            fresh = False
            out.append(unpack.decompress(data))
        waiting = unpack.unused_data
        yield b"".join(out)


def read_archive(stream) -> Iterator[bytes]:
    """Raw records of an archive whose dictionary stands in the leading skippable frame."""
    head = stream.read(8)
    if len(head) < 8:
        raise Malformed("no leading frame")
    magic, n = struct.unpack("<II", head)
    if magic != DICTIONARY_MAGIC:
        raise Malformed("no leading dictionary frame")
    raw = stream.read(n)
    if len(raw) != n:
        raise Malformed("the dictionary is cut short")
    if raw and struct.unpack("<I", raw[:4])[0] == FRAME_MAGIC:  # a dictionary may itself be compressed
        raw = zstandard.ZstdDecompressor().decompressobj().decompress(raw)
    if raw and raw[:4] != ZSTD_DICTIONARY:
        raise Malformed("not a dictionary")
    return frames(stream, zstandard.ZstdCompressionDict(raw) if raw else None)


def write_archives(pages: DataFrame, folder: str, roll_bytes: int = ROLL_BYTES, least: int = 0) -> DataFrame:
    """Write all rows of (page_id, url, html); returns the stored table of archives: path, records."""
    p = pages.select(
        F.col("page_id").cast("long").alias("page_id"),
        F.col("url").cast("string").alias("url"),
        F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary").alias("payload"),
    )
    key = F.sha1("payload")
    firsts = p.where(F.length("payload") >= least).groupBy(key.alias("key")).agg(F.min("page_id").alias("first"), F.count("*").alias("copies"))
    # Only payloads with copies need a join partner; their number of keys is far below that of pages.
    firsts = firsts.where("copies > 1").select(F.col("key").alias("k"), "first")
    p = p.withColumn("key", key).join(firsts, F.col("key") == F.col("k"), "left")
    p = p.select("page_id", "url", "payload", "first", (F.col("k").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))).alias("again"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = pafs.FileSystem.from_uri(folder)

        def made() -> Iterator[bytes]:
            for batch in batches:
                for i in range(batch.num_rows):
                    page, url, payload, first, again = (batch.column(c)[i].as_py() for c in range(5))
                    yield record(page, url, payload, first, again)

        rows, names, counts = made(), [], []
        fs.create_dir(base, recursive=True)
        while (r := next(rows, None)) is not None:
            name = f"part-{uuid.uuid4().hex}.warc.zst"
            ahead = iter([r])
            with fs.open_output_stream(f"{base}/{name}", compression=None) as out:
                counts.append(put_archive(out, _chained(ahead, rows), roll_bytes))
            names.append(f"{folder}/{name}")
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(counts, pa.int64())], names=["path", "records"])

    return stored(p.mapInArrow(run, "path string, records long"), "archives")


def _chained(*parts: Iterator[bytes]) -> Iterator[bytes]:
    for p in parts:
        yield from p


def read_archives(archives: DataFrame) -> DataFrame:
    """One row per record of the archives in column ``path``, checked on the way."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())
        names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
        for batch in batches:
            for path, count in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                fs, at = pafs.FileSystem.from_uri(path)
                with fs.open_input_stream(at, compression=None) as stream:
                    rows, n = [], 0
                    for raw in read_archive(stream):
                        rows.append(summary(raw))
                        n += 1
                        if len(rows) >= 4096:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)
                            rows = []
                    if n != count:
                        raise Malformed(f"{n} records instead of {count}")
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    # A given number of partitions, so that small rows that stand for large files aren't put together.
    spread = archives.select("path", "records").repartition(max(1, min(10_000, archives.count())), "path")
    return spread.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def round_trip(spark: SparkSession, pages: DataFrame, folder: str | None = None, least: int = 0) -> DataFrame:
    """Write the pages' archives and read them back."""
    return read_archives(write_archives(pages, folder or new_path(spark, "warc"), least=least))
