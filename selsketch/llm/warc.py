"""WARC files as a Spark data source: ``spark.read.format("warc")`` and ``df.write.format("warc")``.

Reading plans files, and byte ranges of long compressed files, into partitions of about equal bytes, takes predicates on the record type and on headers down to
the parser, reads a record's headers first and never inflates the rest of a record that isn't wanted: a gzip member says its
own length (the ``sl`` extra field, which the writer sets), and a plain record its Content-Length.  Writing commits by a
manifest, so files of lost or repeated task attempts are never read.
"""

from __future__ import annotations

import base64
import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, Filter, In, InputPartition, IsNotNull, WriterCommitMessage

from .common import Scratch, Sieve, hot_join

SCHEMA = "record_id string, record_type string, target_uri string, date string, refers_to string, payload_digest string, payload_bytes long, payload binary, headers map<string,string>, file string, offset long"
#: Columns that come from a header of their own.
HEADERS = {"record_id": "WARC-Record-ID", "record_type": "WARC-Type", "target_uri": "WARC-Target-URI", "date": "WARC-Date", "refers_to": "WARC-Refers-To", "payload_digest": "WARC-Payload-Digest"}
MANIFEST = "_manifest.json"
_BATCH_BYTES, _PARTITION_BYTES, _FILE_BYTES = 4 << 20, 64 << 20, 256 << 20
_PEEK = 1 << 12


def sha1_base32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _open_fs(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


@dataclass
class Files(InputPartition):
    """(path, from, to): records that start in this range of bytes."""

    parts: list


def _parse(head: bytes) -> dict[str, str]:
    out: dict[str, str] = {}
    last = None
    for line in head.decode("utf-8", "replace").split("\r\n")[1:]:
        if line[:1] in (" ", "\t") and last:
            out[last] += " " + line.strip()
        elif ":" in line:
            last, value = line.split(":", 1)
            last = last.strip()
            out[last] = value.strip()
    return out


def _plain(value: str | None) -> str | None:
    return value[1:-1] if value and value[0] == "<" and value[-1] == ">" else value


def record(headers: dict[str, str], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in headers.items() if v is not None)
    return b"WARC/1.1\r\n" + head.encode() + b"Content-Length: %d\r\n\r\n" % len(block) + block + b"\r\n\r\n"


def member(raw: bytes, level: int) -> bytes:
    """One gzip member whose ``sl`` extra field holds its compressed and its plain length."""
    press = zlib.compressobj(level, zlib.DEFLATED, -15)
    body = press.compress(raw) + press.flush()
    size = 10 + 2 + 12 + len(body) + 8
    return b"\x1f\x8b\x08\x04\0\0\0\0\0\xff" + struct.pack("<H2sHII", 12, b"sl", 8, size & 0xFFFFFFFF, len(raw) & 0xFFFFFFFF) + body + struct.pack("<II", zlib.crc32(raw), len(raw) & 0xFFFFFFFF)


def _first_member(handle, at: int, size: int) -> int:
    """Where the first gzip member that holds a record starts, from ``at`` on."""
    while at < size:
        handle.seek(at)
        data = handle.read(1 << 20)
        found = data.find(b"\x1f\x8b\x08")
        while found >= 0:
            handle.seek(at + found)
            try:
                if zlib.decompressobj(31).decompress(handle.read(_PEEK), 16).startswith(b"WARC/"):
                    return at + found
            except zlib.error:
                pass
            found = data.find(b"\x1f\x8b\x08", found + 1)
        at += max(len(data) - 2, 1)
    return size


def _records(handle, start: int, size: int, compressed: bool, wanted, whole: bool) -> Iterator[tuple[int, dict[str, str], bytes | None]]:
    """(offset, headers, block or None) of the records that start in start..size and whose headers ``wanted`` accepts."""
    at = _first_member(handle, start, size) if start else 0
    while at < size:
        handle.seek(at)
        if not compressed:
            head, more = b"", b"?"
            while b"\r\n\r\n" not in head and more:
                head += (more := handle.read(_PEEK))
            cut = head.find(b"\r\n\r\n")
            if cut < 0:
                return
            headers = _parse(head[:cut].lstrip(b"\r\n"))
            length = int(headers.get("Content-Length", 0))
            if wanted(headers):
                block = None
                if whole:
                    block = head[cut + 4 : cut + 4 + length]
                    block += handle.read(length - len(block)) if len(block) < length else b""
                yield at, headers, block
            lead = len(head) - len(head.lstrip(b"\r\n"))
            at += cut + 4 + length + 4 if not lead else cut + 4 + length
            continue
        first = handle.read(_PEEK)
        if first[:2] != b"\x1f\x8b":
            return
        jump = None
        if first[3] & 4 and first[12:14] == b"sl":
            jump = struct.unpack_from("<I", first, 16)[0]
        inflate, text, fed = zlib.decompressobj(31), b"", len(first)
        text = inflate.decompress(first)
        while b"\r\n\r\n" not in text and not inflate.eof:
            more = handle.read(_PEEK)
            if not more:
                return
            fed += len(more)
            text += inflate.decompress(more)
        cut = text.find(b"\r\n\r\n")
        headers = _parse(text[:cut])
        length = int(headers.get("Content-Length", 0))
        good = wanted(headers)
        parts, have = [text[cut + 4 :]], len(text) - cut - 4
        while not inflate.eof and ((good and whole and have < length) or not jump):
            more = handle.read(1 << 16)
            if not more:
                break
            fed += len(more)
            out = inflate.decompress(more)
            have += len(out)
            if good and whole:
                parts.append(out)
        if good:
            yield at, headers, b"".join(parts)[:length] if whole else None
        at += jump or fed - len(inflate.unused_data)


def _http(block: bytes) -> tuple[dict[str, str], bytes]:
    head, _, body = block.partition(b"\r\n\r\n")
    return _parse(head), body


class WarcReader(DataSourceReader):
    """Options: path; payload = full (default) or none (blocks stay unread, payload null); verify = true recomputes digests."""

    def __init__(self, options: dict, schema):
        self.path, self.payload = options["path"], options.get("payload", "full") == "full"
        self.verify = str(options.get("verify", "false")).lower() == "true"
        self.names = [f.name for f in schema.fields]
        self.wants: list[tuple[str, tuple]] = []

    def pushFilters(self, filters: list[Filter]):
        for f in filters:
            column = f.attribute[0] if hasattr(f, "attribute") and len(f.attribute) == 1 else None
            if column in HEADERS and isinstance(f, EqualTo):
                self.wants.append((column, (f.value,)))
            elif column in HEADERS and isinstance(f, In):
                self.wants.append((column, tuple(f.value)))
            elif column in HEADERS and isinstance(f, IsNotNull):
                self.wants.append((column, ()))
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        store, root = _open_fs(self.path)
        if store.get_file_info(f"{root}/{MANIFEST}").type == fs.FileType.File:
            with store.open_input_stream(f"{root}/{MANIFEST}") as f:
                files = [(f"{self.path.rstrip('/')}/{x['file']}", x["bytes"]) for x in json.loads(f.read())]
        elif store.get_file_info(root).type == fs.FileType.File:
            files = [(self.path, store.get_file_info(root).size)]
        else:
            found = store.get_file_info(fs.FileSelector(root, recursive=True))
            files = [(self.path.rstrip("/") + x.path[len(root.rstrip("/")) :], x.size) for x in found if x.path.endswith((".warc", ".warc.gz"))]
        # a plain file may quote another one, so only compressed members are found from any byte on
        ranges = [(p, lo, min(lo + _PARTITION_BYTES, size)) for p, size in sorted(files) if size for lo in (range(0, size, _PARTITION_BYTES) if p.endswith(".gz") else [0])]
        ranges = [(p, lo, hi if p.endswith(".gz") else None) for p, lo, hi in ranges]
        sizes = dict(files)
        bins: list[list[tuple]] = []
        filled = _PARTITION_BYTES
        for path, lo, hi in ranges:
            held = (sizes[path] if hi is None else hi) - lo
            if filled + held > _PARTITION_BYTES:
                bins.append([])
                filled = 0
            bins[-1].append((path, lo, hi))
            filled += held
        return [Files(b) for b in bins] or [Files([])]

    def _wanted(self, headers: dict[str, str]) -> bool:
        for column, values in self.wants:
            value = _column(headers, column)
            if value is None or (values and value not in values):
                return False
        return True

    def read(self, partition: Files):
        made = pa.schema([(n, _KINDS[n]) for n in self.names])
        rows, held = [], 0
        for path, lo, hi in partition.parts:
            store, at = _open_fs(path)
            with store.open_input_file(at) as handle:
                for offset, headers, block in _records(handle, lo, handle.size() if hi is None else hi, path.endswith(".gz"), self._wanted, self.payload):
                    row = {c: _column(headers, c) for c in HEADERS}
                    payload, size = block, None
                    if "application/http" in headers.get("Content-Type", "") and block is not None:
                        http, payload = _http(block)
                        size = int(http["Content-Length"]) if "Content-Length" in http else len(payload)
                    elif block is not None:
                        size = len(block)
                    if row["record_type"] == "revisit":
                        payload = None
                    elif self.verify and payload is not None:
                        size, row["payload_digest"] = len(payload), sha1_base32(payload)
                    row |= {"payload": payload, "payload_bytes": size, "headers": list(headers.items()), "file": path, "offset": offset}
                    rows.append([row[n] for n in self.names])
                    held += len(block or b"") + 500
                    if held >= _BATCH_BYTES:
                        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), made, strict=True)], schema=made)
                        rows, held = [], 0
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), made, strict=True)], schema=made)


def _column(headers: dict[str, str], column: str) -> str | None:
    value = _plain(headers.get(HEADERS[column]))
    return value.split(":", 1)[1] if column == "payload_digest" and value and ":" in value else value


_KINDS = {"record_id": pa.string(), "record_type": pa.string(), "target_uri": pa.string(), "date": pa.string(), "refers_to": pa.string(), "payload_digest": pa.string(), "payload_bytes": pa.int64(), "payload": pa.binary(), "headers": pa.map_(pa.string(), pa.string()), "file": pa.string(), "offset": pa.int64()}


@dataclass
class Written(WriterCommitMessage):
    files: list


class WarcWriter(DataSourceArrowWriter):
    """Input columns: record_id, record_type (response or revisit), target_uri, payload; for revisits refers_to,
    payload_digest and payload_bytes.  Options: path; date; level (gzip, 0 = plain files)."""

    def __init__(self, options: dict, overwrite: bool):
        self.path, self.date, self.level = options["path"].rstrip("/"), options.get("date", "2024-01-01T00:00:00Z"), int(options.get("level", 1))
        self.overwrite = overwrite

    def _blocks(self, batches) -> Iterator[bytes]:
        for batch in batches:
            for row in batch.to_pylist():
                payload = row.get("payload")
                digest, size = row.get("payload_digest"), row.get("payload_bytes")
                revisit = row["record_type"] == "revisit"
                if not revisit:
                    payload = payload or b""
                    digest, size = sha1_base32(payload), len(payload)
                http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
                target = "".join((row.get("target_uri") or "").split())  # a line break would end the header
                headers = {"WARC-Type": row["record_type"], "WARC-Record-ID": f"<{row['record_id']}>", "WARC-Target-URI": target or None, "WARC-Date": self.date, "WARC-Payload-Digest": f"sha1:{digest}"}
                if revisit:
                    headers |= {"WARC-Refers-To": f"<{row['refers_to']}>", "WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"}
                yield record(headers | {"Content-Type": "application/http; msgtype=response"}, http if revisit else http + payload)

    def write(self, iterator):
        store, root = _open_fs(self.path)
        store.create_dir(root, recursive=True)
        files, handle = [], None
        name = size = None
        for raw in self._blocks(iterator):
            if handle is None or size > _FILE_BYTES:
                if handle:
                    handle.close()
                    files.append({"file": name, "bytes": size})
                name = f"part-{uuid.uuid4().hex}.warc" + ".gz" * bool(self.level)
                handle, size = store.open_output_stream(f"{root}/{name}", compression=None), 0
                info = record({"WARC-Type": "warcinfo", "WARC-Record-ID": f"<urn:uuid:{uuid.uuid4()}>", "WARC-Date": self.date, "WARC-Filename": name, "Content-Type": "application/warc-fields"}, b"format: WARC File Format 1.1\r\n")
                size += handle.write(member(info, self.level) if self.level else info) or 0
            data = member(raw, self.level) if self.level else raw
            handle.write(data)
            size += len(data)
        if handle:
            handle.close()
            files.append({"file": name, "bytes": store.get_file_info(f"{root}/{name}").size})
        return Written(files)

    def commit(self, messages):
        store, root = _open_fs(self.path)
        files = [f for m in messages if m for f in m.files]
        store.create_dir(root, recursive=True)
        if not self.overwrite and store.get_file_info(f"{root}/{MANIFEST}").is_file:
            with store.open_input_stream(f"{root}/{MANIFEST}") as f:
                files = json.loads(f.read()) + files
        with store.open_output_stream(f"{root}/{MANIFEST}") as f:
            f.write(json.dumps(files).encode())

    def abort(self, messages):
        store, root = _open_fs(self.path)
        for f in [f for m in messages if m for f in m.files]:
            store.delete_file(f"{root}/{f['file']}")


class WarcSource(DataSource):
    """See WarcReader and WarcWriter for options."""

    @classmethod
    def name(cls):
        return "warc"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return WarcReader(self.options, schema)

    def writer(self, schema, overwrite):
        return WarcWriter(self.options, overwrite)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)


def with_revisits(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """pages(page_id, url, html) -> columns for the writer.

    Of equal payloads of at least ``least_bytes``, the page of the largest page_id is the response, the others revisit it.
    Rows that repeat this page_id with the same payload are responses too.  A null html is an empty payload; a null page_id
    is smaller than any other, and where all are null each is a response.  Other columns are ignored.

    Roles are found on digests alone.  A payload is shuffled only where its page is the response of a group, or where a Sieve
    can't tell: pages of a payload of their own are written straight from the scan, revisits need no payload.
    """
    scratch = Scratch(pages.sparkSession)
    payload = F.encode(F.coalesce(F.col("html"), F.lit("")), "UTF-8")
    page = pages.select(F.col("page_id").cast("long"), F.col("url").alias("target_uri"), payload.alias("payload"))
    page = page.withColumn("digest", F.sha1("payload")).withColumn("payload_bytes", F.length("payload").cast("long"))
    groups = page.where(F.col("payload_bytes") >= least_bytes).groupBy("digest", "payload_bytes").agg(F.max("page_id").alias("response"), F.count("*").alias("w"))
    groups = scratch.save(groups.where("w > 1 AND response IS NOT NULL"), "groups")
    key = F.xxhash64("digest", "payload_bytes")
    copied = Sieve(groups.select(key.alias("k")), "k").maybe(key)

    slim = page.where(copied).select("page_id", "target_uri", "digest", "payload_bytes")
    revisit = F.col("response").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("response"))
    roles = scratch.save(hot_join(slim, groups, ["digest", "payload_bytes"], "w", "left").withColumn("revisit", revisit), "roles")
    full = roles.where("NOT revisit").select(F.col("page_id").alias("_id"), F.col("digest").alias("_digest"), F.col("payload_bytes").alias("_bytes")).distinct()
    own = F.xxhash64("page_id", "digest", "payload_bytes")
    chosen = Sieve(full.select(F.xxhash64("_id", "_digest", "_bytes").alias("k")), "k").maybe(own)
    same = F.col("page_id").eqNullSafe(F.col("_id")) & (F.col("digest") == F.col("_digest")) & (F.col("payload_bytes") == F.col("_bytes"))

    urn = lambda c: F.concat(F.lit("urn:page:"), F.coalesce(F.col(c).cast("string"), F.lit("none")))
    named = lambda rows, kind, refers, body: rows.select(
        urn("page_id").alias("record_id"), F.lit(kind).alias("record_type"), "target_uri", refers.alias("refers_to"), _base32("digest").alias("payload_digest"), "payload_bytes", body.alias("payload")
    )
    none = F.lit(None).cast("string")
    parts = [page.where(~copied), page.where(copied).where(chosen).join(full.hint("merge"), same, "left_semi")]
    responses = [named(rows, "response", none, F.col("payload")) for rows in parts]
    return responses[0].union(responses[1]).union(named(roles.where("revisit"), "revisit", urn("response"), F.lit(None).cast("binary")))


def _base32(hex_column: str):
    """RFC 4648 text of a 40-digit hexadecimal column, five bits at a time."""
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
    bits = F.concat(*[F.lpad(F.conv(F.substring(hex_column, 1 + 10 * i, 10), 16, 2), 40, "0") for i in range(4)])
    at = lambda i: F.conv(F.substring(bits, i * 5 + 1, 5), 2, 10).cast("int") + 1
    return F.array_join(F.transform(F.sequence(F.lit(0), F.lit(31)), lambda i: F.substring(F.lit(letters), at(i), F.lit(1))), "")


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to: written as archives, then read back."""
    register(spark)
    scratch = Scratch(spark)
    records = with_revisits(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    records.write.format("warc").mode("append").save(at := scratch.path("warc"))
    back = spark.read.format("warc").option("verify", "true").load(at).where(F.col("record_type").isin("response", "revisit"))
    page = lambda c: F.regexp_extract(c, r"^urn:page:(-?\d+)$", 1).try_cast("long")
    return back.select(page("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", page("refers_to").alias("refers_to"))


_LETTER = ", ".join(f"substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (v[{g + 1}] >> {s}) % 32 + 1, 1)" for g in range(8) for s in (15, 10, 5, 0))
_GROUPS = ", ".join(f"('0x' || substr(x, {5 * g + 1}, 5))::BIGINT" for g in range(8))
OP1_SQL = f"""
WITH s AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS x,
                  max(page_id) OVER (PARTITION BY coalesce(html, '')) AS m FROM pages),
b AS (SELECT *, [{_GROUPS}] AS v FROM s)
SELECT page_id, payload_bytes, concat({_LETTER}) AS payload_digest,
       CASE WHEN m = page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN m <> page_id THEN m END AS refers_to
FROM b
"""
