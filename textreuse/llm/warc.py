"""Zstandard WARC archives: one frame a record, dictionary in a leading skippable frame.

Layout as in the public WARC-Zstandard note: a file may start with a skippable frame
(magic 0x184D2A5D) that holds a dictionary, itself compressed or not; every record
after it is one frame made with that dictionary.

Writing: a task writes the rows of its partition in the order of their places in the
table, so that a task that runs again writes the same files. It fills archives up to a
bounded size, trains the dictionary of an archive on its own first records, writes
under a hidden name and renames. Payloads move only if the revisits are too many to
broadcast. Reading: an archive is one task's work at most; frames are decoded one at a
time, so memory is bounded by an archive and a record. Every fault becomes a row with
``error``; a damaged frame ends its archive, a wrong header or length does not.
:func:`round_trip` fails on any.

Revisits: of records with equal payloads of at least ``revisit_bytes`` the one with
the largest id is the response; the others carry only HTTP headers and refer to it.
A revisit is a matter of the row: rows of one id and different payloads each refer to
the response of their own payload.

Cases: a null payload is empty; a null id is written as ``null`` and read as null, and
is never a revisit. Rows that repeat are written each; those of the largest id are all
responses. Ids that tie with the largest of their payload are responses. Empty tables
write no archive and read as an empty table. Payloads may be of any length below 2 GB.
Other columns of the input are passed by, whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator

import pandas as pd
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, small_or_shuffled

DICTIONARY_MAGIC = 0x184D2A5D
FRAME_MAGIC = 0xFD2FB528
SKIPPABLE = range(0x184D2A50, 0x184D2A60)
VERSION = b"WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
REQUIRED = ("warc-record-id", "content-length", "warc-date", "warc-type")
EPOCH = "1970-01-01T00:00:00Z"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """A response with its payload, or a revisit that names the response."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    uri = "".join(c for c in url or "" if c.isprintable() and c != " ") or "urn:page:unknown"
    name = "null" if page_id is None else str(page_id)
    lines = [
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:page:{name}>",
        f"WARC-Date: {EPOCH}",
        f"WARC-Target-URI: {uri}",
        "Content-Type: application/http; msgtype=response",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"WARC-Block-Digest: sha1:{base32_sha1(block)}",
    ]
    if refers_to is not None:
        lines += [f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {PROFILE}"]
    head = "\r\n".join([VERSION.decode(), *lines, f"Content-Length: {len(block)}", "", ""]).encode()
    return head + block + b"\r\n\r\n"


def archive(records: list[bytes], level: int = 3, dictionary_bytes: int = 32_768) -> bytes:
    """An archive of the records. Without enough material for a dictionary it has none."""
    made, out = None, []
    try:
        if len(records) >= 16:
            made = zstandard.train_dictionary(dictionary_bytes, [r[:16_384] for r in records[:2_000]])
    except zstandard.ZstdError:
        made = None
    if made is not None:
        content = zstandard.ZstdCompressor(level=level).compress(made.as_bytes())
        out.append(struct.pack("<II", DICTIONARY_MAGIC, len(content)) + content)
    # A compressor for the whole archive; the size and a checksum stand in each frame.
    make = zstandard.ZstdCompressor(level=level, dict_data=made, write_checksum=True, write_content_size=True)
    return b"".join([*out, *(make.compress(r) for r in records)])


class Damaged(ValueError):
    pass


def leading_dictionary(data: memoryview) -> tuple[zstandard.ZstdCompressionDict | None, int]:
    """The dictionary of an archive, and where its records start."""
    if len(data) < 8:
        return None, 0
    magic, size = struct.unpack_from("<II", data)
    if magic != DICTIONARY_MAGIC:
        return None, 0
    if 8 + size > len(data):
        raise Damaged("dictionary frame is cut off")
    content = bytes(data[8 : 8 + size])
    if content[:4] == struct.pack("<I", FRAME_MAGIC):
        content = zstandard.ZstdDecompressor().decompressobj().decompress(content)
    return zstandard.ZstdCompressionDict(content), 8 + size


def frames(data: bytes, most: int = 1 << 31, step: int = 65_536) -> Iterator[bytes]:
    """The content of each frame in turn; later skippable frames are passed over."""
    view = memoryview(data)
    made, at = leading_dictionary(view)
    tool = zstandard.ZstdDecompressor(dict_data=made) if made else zstandard.ZstdDecompressor()
    while at < len(view):
        if len(view) - at < 4:
            raise Damaged("bytes after the last frame")
        magic = struct.unpack_from("<I", view, at)[0]
        if magic in SKIPPABLE:
            if len(view) - at < 8:
                raise Damaged("skippable frame is cut off")
            at += 8 + struct.unpack_from("<I", view, at + 4)[0]
            continue
        if magic != FRAME_MAGIC:
            raise Damaged("no frame where one should start")
        one, parts, made_bytes = tool.decompressobj(), [], 0
        while not one.eof:
            if at >= len(view):
                raise Damaged("frame is cut off")
            taken = view[at : at + step]
            try:
                parts.append(one.decompress(taken))
            except zstandard.ZstdError as e:
                raise Damaged(str(e)) from e
            made_bytes += len(parts[-1])
            if made_bytes > most:
                raise Damaged("record is larger than allowed")
            at += len(taken) - len(one.unused_data)
        yield b"".join(parts)


def _headers(raw: bytes) -> dict[str, str]:
    out = {}
    for line in raw.split(b"\r\n"):
        name, colon, value = line.partition(b":")
        if not colon:
            raise ValueError("header without colon")
        out.setdefault(name.strip().lower().decode("ascii", "replace"), value.strip().decode("utf-8", "replace"))
    return out


def _page(uri: str | None) -> int | None:
    name = (uri or "").strip("<>").rpartition(":")[2]
    return int(name) if name.lstrip("-").isdigit() else None


def parse(content: bytes) -> dict:
    """A record's fields; ``error`` tells the first fault, if any."""
    row = dict.fromkeys(("page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload", "error"))
    try:
        head, gap, rest = content.partition(b"\r\n\r\n")
        first, _, lines = head.partition(b"\r\n")
        if not gap or first not in (b"WARC/1.0", VERSION):
            raise ValueError("no WARC header")
        fields = _headers(lines)
        if missing := [n for n in REQUIRED if n not in fields]:
            raise ValueError(f"header lacks {', '.join(missing)}")
        row |= {"page_id": _page(fields["warc-record-id"]), "url": fields.get("warc-target-uri"), "record_type": fields["warc-type"], "refers_to": _page(fields.get("warc-refers-to"))}
        size = int(fields["content-length"])
        if len(rest) != size + 4 or rest[size:] != b"\r\n\r\n":
            raise ValueError("length of the block differs from Content-Length")
        block = rest[:size]
        if fields.get("warc-block-digest", "").removeprefix("sha1:") not in ("", base32_sha1(block)):
            raise ValueError("block digest differs")
        http, gap, payload = block.partition(b"\r\n\r\n")
        if not gap:
            raise ValueError("no HTTP header in the block")
        told = int(_headers(http.partition(b"\r\n")[2])["content-length"])
        digest = fields.get("warc-payload-digest", "").removeprefix("sha1:")
        row |= {"payload_bytes": told, "payload_digest": base64.b32decode(digest).hex() if digest else None}
        if row["record_type"] == "response":
            if len(payload) != told:
                raise ValueError("length of the payload differs from its Content-Length")
            if digest and base32_sha1(payload) != digest:
                raise ValueError("payload digest differs")
            row["payload"] = payload
        elif row["record_type"] == "revisit" and (row["refers_to"] is None or payload):
            raise ValueError("revisit without a response, or with a payload")
    except (ValueError, KeyError) as e:
        row["error"] = str(e) or type(e).__name__
    return row


def write_archives(pages: DataFrame, folder: str, payload: str = "html", key: str = "page_id", url: str = "url", archive_bytes: int = 32 << 20, revisit_bytes: int = 1000) -> None:
    """Write a record for each row below ``folder`` (any URI that pyarrow can open)."""
    body = F.coalesce(F.encode(F.col(payload), "UTF-8"), F.lit(b""))
    rows = pages.select(F.monotonically_increasing_id().alias("_at"), F.col(key).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), body.alias("payload"))
    rows = rows.withColumn("_digest", F.sha1("payload"))
    digests = rows.where(F.octet_length("payload") >= revisit_bytes).select("page_id", "_digest")
    latest = digests.groupBy("_digest").agg(F.max("page_id").alias("refers_to"), F.min("page_id").alias("_least")).where("_least < refers_to").drop("_least")
    revisits = digests.distinct().join(latest, "_digest").where("page_id < refers_to")
    revisits = Scratch(pages.sparkSession, "warc-revisits").cut(revisits, "revisits")
    # (page_id, digest) names a payload's revisit, so that a row can neither match twice nor take another's response.
    made = rows.join(small_or_shuffled(revisits), ["page_id", "_digest"], "left").select("_at", "page_id", "url", "payload", "refers_to")
    dealt = made.sortWithinPartitions("_at").drop("_at").withColumn("_part", F.spark_partition_id())

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyarrow import fs

        store, where = fs.FileSystem.from_uri(folder)
        held, size, done, part = [], 0, 0, 0

        def put() -> dict:
            nonlocal held, size, done
            name = f"{where}/part-{part:06d}-{done:05d}.warc.zst"
            hidden = f"{where}/_{part:06d}-{done:05d}-{uuid.uuid4().hex}"
            with store.open_output_stream(hidden) as out:
                out.write(archive(held))
            if store.get_file_info(name).type != fs.FileType.NotFound:
                store.delete_file(name)  # of an attempt that was lost after it wrote the same
            store.move(hidden, name)
            told = {"archive": name, "records": len(held)}
            held, size, done = [], 0, done + 1
            return told

        for batch in batches:
            told = []
            for page_id, link, body, to, part in batch.itertuples(index=False):
                held.append(record(None if pd.isna(page_id) else int(page_id), link, body, base32_sha1(body), None if pd.isna(to) else int(to)))
                size += len(held[-1])
                if size >= archive_bytes:
                    told.append(put())
            if told:
                yield pd.DataFrame(told)
        if held:
            yield pd.DataFrame([put()])

    from pyarrow import fs

    store, where = fs.FileSystem.from_uri(folder)
    store.create_dir(where, recursive=True)
    dealt.mapInPandas(run, "archive string, records long").agg(F.sum("records")).collect()


RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary, error string"


def read_archives(spark: SparkSession, folder: str, payloads: bool = True) -> DataFrame:
    """A row for each record of the archives below ``folder`` (any store that Spark reads)."""
    fields = [f for f in ("page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload", "error") if payloads or f != "payload"]
    schema = RECORD if payloads else RECORD.replace("payload binary, ", "")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def frame(rows: list[dict]) -> pd.DataFrame:
            out = pd.DataFrame(rows, columns=fields)
            return out.astype({c: "Int64" for c in ("page_id", "payload_bytes", "refers_to")})

        for batch in batches:
            for data in batch["content"]:
                rows, size = [], 0
                try:
                    for content in frames(data):
                        rows.append(parse(content))
                        size += len(content)
                        if size >= 8 << 20:
                            yield frame(rows)
                            rows, size = [], 0
                except Damaged as e:
                    rows.append({"error": str(e)})
                yield frame(rows)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.zst").load(folder)
    return files.select("content").mapInPandas(run, schema)


def round_trip(pages: DataFrame, payload: str = "html", key: str = "page_id", url: str = "url") -> DataFrame:
    """Write the pages as archives below the shared folder and read their records back. Reading fails on a damaged record."""
    folder = Scratch(pages.sparkSession, "warc").path("archives")
    write_archives(pages, folder, payload, key, url)
    return sound(read_archives(pages.sparkSession, folder, payloads=False))


def sound(records: DataFrame) -> DataFrame:
    """``records`` as they are; a row with an ``error`` fails the job when it is read."""
    fault = F.raise_error(F.concat(F.lit("damaged archive: "), F.col("error"))).cast("string")
    checked = F.when(F.col("error").isNotNull(), fault).otherwise(F.col("record_type"))
    return records.withColumn("record_type", checked)
