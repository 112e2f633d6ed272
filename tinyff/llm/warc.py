"""WARC archives: writing, normalising monolithic gzip files, reading by index.

A monolithic archive is one gzip stream over all records, which cannot be entered
in the middle. The normaliser inflates such a stream once, front to back, with a
bounded buffer; every record becomes a gzip member of its own, and a sidecar file
lists each member's archive, offset and length. An archive's name stands in the
gzip header of its first member, so that files may have any path. Readers enter
archives at the offsets of the sidecar, inflate just the listed members and raise
an error where archive and sidecar differ. Archives and sidecars are real files
written through Spark's writers (one value a file; the writer ends a file with a
zero byte, which gzip readers take as padding), so any file system that Spark
reaches will do.

Of records with equal payloads of at least ``least`` bytes, the one with the
smallest id is a response and the others are revisits that carry the HTTP header
but no payload.

Defined cases: a null payload is empty; null ids sort after all others (equal
payloads under null ids only are all responses, as are repeated rows of the first
id); line breaks in a URL are dropped; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import materialise, scratch_path, small_side
from .exact_dedup import group_digests

#: Inflated bytes after which an archive is closed.
ARCHIVE_BYTES = 64 << 20
LEAST_PAYLOAD = 100
#: Characters of an archive's name, and where they stand in the header of a member that has a name (from 1).
NAME_CHARS, NAME_AT = 38, 11
_DATE = "2024-01-01T00:00:00Z"
_END = b"\r\n\r\n"
_RESULT = "archive string, offset long, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC record; a revisit if ``refers_to`` is given."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Target-URI: {''.join((url or '').split(chr(10))).replace(chr(13), '')}", f"WARC-Date: {_DATE}", f"WARC-Payload-Digest: sha256:{digest}"]
    if refers_to is not None:
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + _END + block + _END


def headers(raw: bytes) -> dict[str, str]:
    return {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in raw.decode("utf-8", "replace").split("\r\n")[1:])}


def records_of(content: bytes, step: int = 1 << 18) -> Iterator[bytes]:
    """The records of gzip data (any number of members) in order, inflating ``step`` bytes at a time."""
    inflate, held, at, padded = zlib.decompressobj(31), bytearray(), 0, False
    need = None  # size of the record at the front, once its header is there
    while True:
        while True:
            if need is None:
                end = held.find(_END)
                if end < 0:
                    break
                need = end + 4 + int(headers(bytes(held[:end])).get("content-length", 0)) + 4
            if len(held) < need:
                break
            yield bytes(held[:need])
            del held[:need]
            need = None
        if padded or (at >= len(content) and not inflate.unconsumed_tail):
            if held:
                raise ValueError(f"{len(held)} bytes of a broken record at the end of the archive")
            return
        if inflate.eof:
            while at < len(content) and content[at] == 0:  # padding between or after members
                at += 1
            if at >= len(content):
                padded = True
                continue
            inflate = zlib.decompressobj(31)
        held += inflate.decompress(content[at : at + step])
        at = min(at + step, len(content)) - len(inflate.unused_data)


def member(raw: bytes, level: int = 1, name: str | None = None) -> bytes:
    """One gzip member; ``name`` goes into the file-name field of its header."""
    pack = zlib.compressobj(level, zlib.DEFLATED, -15)
    head = struct.pack("<4BIBB", 0x1F, 0x8B, 8, 8 if name else 0, 0, 0, 255) + (name.encode() + b"\0" if name else b"")
    return head + pack.compress(raw) + pack.flush() + struct.pack("<II", zlib.crc32(raw), len(raw) & 0xFFFFFFFF)


def normalise_archive(content: bytes, stem: str, most: int = ARCHIVE_BYTES, level: int = 1) -> Iterator[tuple[str, bytes, list[str]]]:
    """Archives of about ``most`` inflated bytes with a member per record, and their index lines: archive, offset, length, type, id."""
    part, out, lines, size = 0, bytearray(), [], 0
    for raw in records_of(content):
        name = f"{stem}-{part:05d}"
        head = headers(raw[: raw.index(_END)])
        made = member(raw, level, None if lines else name)
        lines.append(f"{name} {len(out)} {len(made)} {head['warc-type']} {head['warc-record-id'].strip('<>')}")
        out += made
        size += len(raw)
        if size >= most:
            yield name, bytes(out), lines
            part, out, lines, size = part + 1, bytearray(), [], 0
    if lines:
        yield name, bytes(out), lines


def read_member(content: bytes, offset: int, length: int) -> bytes:
    """The record of exactly one gzip member at ``offset``."""
    inflate = zlib.decompressobj(31)
    raw = inflate.decompress(content[offset : offset + length])
    if not inflate.eof or inflate.unused_data:
        raise ValueError(f"no gzip member of {length} bytes stands at {offset}")
    return raw


def parse(raw: bytes) -> tuple[int | None, int, str, str, int | None]:
    """(id, payload bytes, digest, type, refers to) of one record; a response's digest is checked against its payload."""
    cut = raw.index(_END)
    head, block = headers(raw[:cut]), raw[cut + 4 : -4]
    http = block.index(_END)
    size, digest = int(headers(block[:http])["content-length"]), head["warc-payload-digest"].removeprefix("sha256:")
    number = lambda s: int(s) if (s := s.strip("<>").removeprefix("urn:page:")) else None
    refers = number(head["warc-refers-to"]) if head["warc-type"] == "revisit" else None
    if refers is None and hashlib.sha256(payload := block[http + 4 :]).hexdigest() != digest or refers is None and len(payload) != size:
        raise ValueError(f"payload of {head['warc-record-id']} does not match its digest")
    return number(head["warc-record-id"]), size, digest, head["warc-type"], refers


def revisits(pages: DataFrame, id_col: str, payload_col: str, least: int = LEAST_PAYLOAD) -> DataFrame:
    """(id, digest, refers_to) of every record whose payload an earlier id has; frequent payloads are decided without a shuffle."""
    digest = F.unhex(F.sha2(F.coalesce(F.col(payload_col), F.lit("")), 256))
    base = materialise(pages.where(F.octet_length(payload_col) >= least).select(F.col(id_col).alias("id"), digest.alias("digest")), "payloads")
    found = group_digests(base, pick=F.min).where("group_size > 1 AND keep_id IS NOT NULL AND NOT (id <=> keep_id)")
    return materialise(found.select("id", F.lower(F.hex("digest")).alias("digest"), F.col("keep_id").alias("refers_to")).distinct(), "revisits")


def write_monolithic(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", most: int = ARCHIVE_BYTES, least: int = LEAST_PAYLOAD, level: int = 1) -> None:
    """Writes monolithic gzip archives, one file each, to the folder ``path``."""
    digest = F.sha2(F.coalesce(F.col(payload_col), F.lit("")), 256).alias("digest")
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).alias("url"), F.coalesce(F.col(payload_col), F.lit("")).alias("payload"), digest)
    again = small_side(revisits(pages, id_col, payload_col, least)).withColumnsRenamed({"id": "rid", "digest": "rdigest"})
    rows = rows.join(again, F.col("id").eqNullSafe(F.col("rid")) & (F.col("digest") == F.col("rdigest")), "left").select("id", "url", F.col("payload").cast("binary").alias("payload"), "digest", F.col("refers_to").cast("long").alias("refers_to"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, stream, size = [], zlib.compressobj(level, zlib.DEFLATED, 31), 0
        for batch in batches:
            for values in zip(*batch.columns, strict=True):
                raw = record(*(v.as_py() for v in values))
                out.append(stream.compress(raw))
                size += len(raw)
                if size >= most:
                    yield pa.record_batch({"value": pa.array([b"".join([*out, stream.flush()])], pa.binary())})
                    out, stream, size = [], zlib.compressobj(level, zlib.DEFLATED, 31), 0
        if size:
            yield pa.record_batch({"value": pa.array([b"".join([*out, stream.flush()])], pa.binary())})

    packed = rows.mapInArrow(pack, "value binary").select(F.col("value").cast("string").alias("value"))
    packed.write.option("maxRecordsPerFile", 1).option("lineSep", "\0").text(path)


def normalise(spark: SparkSession, source: str, target: str, most: int = ARCHIVE_BYTES, level: int = 1) -> None:
    """Normalises every archive file of the folder ``source`` into ``target``: ``kind=warc`` and ``kind=index``, a file each for an archive."""
    files = spark.read.format("binaryFile").load(source).select("path", "content")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, content in zip(*batch.columns, strict=True):
                stem = hashlib.md5(path.as_py().rpartition("/")[2].encode()).hexdigest()
                for _, body, lines in normalise_archive(content.as_py(), stem, most, level):
                    for kind, value in (("warc", body), ("index", "\n".join(lines).encode())):
                        yield pa.record_batch({"kind": [kind], "value": pa.array([value], pa.binary())})

    done = files.mapInArrow(run, "kind string, value binary").select("kind", F.col("value").cast("string").alias("value"))
    done.write.partitionBy("kind").option("maxRecordsPerFile", 1).option("lineSep", "\0").text(target)


def read_index(spark: SparkSession, target: str) -> DataFrame:
    """(archive, offset, length, record_type, record_id) from the sidecars."""
    lines = spark.read.schema("value string").text(f"{target}/kind=index").select(F.split(F.regexp_replace("value", "\0", ""), " ").alias("v")).where("size(v) = 5")
    return lines.select(F.col("v")[0].alias("archive"), F.col("v")[1].cast("long").alias("offset"), F.col("v")[2].cast("long").alias("length"), F.col("v")[3].alias("record_type"), F.col("v")[4].alias("record_id"))


def _read_archive(name: str, content: bytes, entries: list[dict] | None, whole: bool) -> list[tuple]:
    """The listed members of one archive, parsed; errors name what differs. ``whole``: the list must cover the archive."""
    if entries is None:
        raise ValueError(f"archive {name} has no index")
    found, stop = [], 0
    for e in entries:
        if whole and e["offset"] != stop:
            raise ValueError(f"the index of archive {name} leaves out or repeats bytes from {min(stop, e['offset'])}")
        raw = read_member(content, e["offset"], e["length"])
        row, head = parse(raw), headers(raw[: raw.index(_END)])
        if (head["warc-type"], head["warc-record-id"].strip("<>")) != (e["record_type"], e["record_id"]):
            raise ValueError(f"archive {name} has another record at {e['offset']} than its index")
        found.append((e["offset"], *row))
        stop = e["offset"] + e["length"]
    if whole and content[stop:].strip(b"\0"):
        raise ValueError(f"the index of archive {name} ends at {stop}, before its last record")
    return found


def read_records(spark: SparkSession, target: str, only: Column | None = None) -> DataFrame:
    """The records of the normalised archives, entered at the offsets of the sidecar index; ``only``: a condition on index rows.

    Without a condition, index and archives must cover each other: whatever one lacks is an error. The lists of
    members are broadcast if they are small; otherwise archives are shuffled to them.
    """
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{target}/kind=warc")
    if not folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder):
        return spark.createDataFrame([], _RESULT)  # no record was written
    files = spark.read.format("binaryFile").load(f"{target}/kind=warc").select(F.substring("content", NAME_AT, NAME_CHARS).cast("string").alias("archive"), "content")
    index = read_index(spark, target) if only is None else read_index(spark, target).where(only)
    lists = index.groupBy("archive").agg(F.sort_array(F.collect_list(F.struct("offset", "length", "record_type", "record_id"))).alias("entries"))  # bounded by an archive
    lists, whole = materialise(lists, "archive-lists"), only is None
    listed, there = lists.count(), spark.read.format("binaryFile").load(f"{target}/kind=warc").select("path").count()
    if whole and listed != there:  # every file is one archive, and one without a list is an error below
        raise ValueError(f"the index lists {listed} archives, but there are {there}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content, entries in zip(*batch.columns, strict=True):
                found = _read_archive(name.as_py(), content.as_py(), entries.as_py(), whole)
                cols = [pa.array(c, t) for c, t in zip(zip(*found, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([name.as_py()] * len(found)), *cols], names=[c.split()[0] for c in _RESULT.split(", ")])

    return files.join(small_side(lists), "archive", "left" if whole else "inner").select("archive", "content", "entries").mapInArrow(run, _RESULT)


def round_trip(pages: DataFrame, folder: str | None = None, most: int = ARCHIVE_BYTES) -> DataFrame:
    """Writes ``pages`` as monolithic archives, normalises them and reads the records back; without ``folder`` the monolithic ones go once they are normalised."""
    spark, scratch = pages.sparkSession, folder is None
    folder = folder or scratch_path(spark, "warc")
    write_monolithic(pages, f"{folder}/monolithic", most=most)
    normalise(spark, f"{folder}/monolithic", f"{folder}/records", most)
    if scratch:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{folder}/monolithic")
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return read_records(spark, f"{folder}/records").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
