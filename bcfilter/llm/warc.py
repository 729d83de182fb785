"""Legacy web archives: write and parse ARC files, convert them to WARC, read WARC files back.

ARC files hold a version block that names the fields of the header lines that follow; each record is one header line
with a declared length and so many bytes. The converter parses the lines of either version, follows the lengths,
and writes gzipped WARC records with identifiers (UUIDs derived from file and offset), ISO dates, types and SHA-1
digests. A payload that several records share is stored once, as ``response``; the others become ``revisit`` records
that refer to it. The deduplication is a grouped aggregation over digests; payloads never pass a shuffle, the writer
goes back to the ARC file by offset.

Files go to the shared folder under names that are unique to the attempt, and count only once they are listed in the
manifest that Spark commits, so a lost executor leaves at most an unlisted file. Folders may be on any file system
that pyarrow knows.

Defined results: null html is an empty payload; null url becomes ``urn:unknown``; white space in URLs is
percent-encoded; repeated rows are records of their own, of which one is the response; a null page_id sorts last.
"""

from __future__ import annotations

import base64
import datetime
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, new_path

ARC_FIELDS = {
    1: "URL IP-address Archive-date Content-type Archive-length",
    2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length",
}
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
ROLL_BYTES = 64 << 20


def _fs(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else "file://" + path)


def _create(folder: str, name: str):
    """Folder may be new; the stream and the full name."""
    full = f"{folder}/{name}"
    fs, inner = _fs(full)
    fs.create_dir(inner.rsplit("/", 1)[0], recursive=True)
    return fs.open_output_stream(inner, compression=None), full


def digest32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def safe_url(url) -> str:
    if not isinstance(url, str) or not url:
        return "urn:unknown"
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)


def http_block(page_id, payload: bytes) -> bytes:
    own = "" if page_id is None else f"X-Page-Id: {page_id}\r\n"
    return f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=UTF-8\r\nContent-Length: {len(payload)}\r\n{own}\r\n".encode() + payload


def arc_header(version: int, url: str, date14: str, block: bytes, name: str, offset: int) -> bytes:
    values = {
        "URL": url, "IP-address": "0.0.0.0", "Archive-date": date14, "Content-type": "text/html", "Result-code": "200",
        "Checksum": hashlib.md5(block).hexdigest(), "Location": "-", "Offset": str(offset), "Filename": name, "Archive-length": str(len(block)),
    }
    return " ".join(values[f] for f in ARC_FIELDS[version].split()).encode() + b"\n"


def gzip_member(data: bytes) -> bytes:
    z = zlib.compressobj(4, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


class ArcFile:
    """Writes one ARC file, each record a gzip member; the first record is the version block."""

    def __init__(self, folder: str, version: int, date14: str):
        self.version, self.date14, self.records = version, date14, 0
        self.name = f"{uuid.uuid4().hex}.arc.gz"
        self.out, self.path = _create(folder, self.name)
        body = f"{version} 0 bcfilter\n{ARC_FIELDS[version]}\n\n".encode()
        self.at = 0
        self._put(f"filedesc://{self.name} 0.0.0.0 {date14} text/plain {len(body)}\n".encode() + body + b"\n")

    def _put(self, data: bytes) -> None:
        member = gzip_member(data)
        self.out.write(member)
        self.at += len(member)

    def add(self, url: str, block: bytes) -> None:
        self._put(arc_header(self.version, url, self.date14, block, self.name, self.at) + block + b"\n")
        self.records += 1


def write_arc(pages: DataFrame, folder: str, date14: str = "20240101000000", roll: int = ROLL_BYTES) -> DataFrame:
    """``pages(page_id, url, html)`` as ARC files, rows by turns in version 1 and 2; the manifest of the files."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        files: dict[int, ArcFile] = {}
        n = 0
        for rows in batches:
            done = []
            for page_id, url, html in zip(rows["page_id"], rows["url"], rows["html"]):
                version = 1 + n % 2
                n += 1
                f = files.get(version) or files.setdefault(version, ArcFile(folder, version, date14))
                f.add(safe_url(url), http_block(page_id, (html or "").encode()))
                if f.at >= roll:
                    f.out.close()
                    done.append((f.path, f.version, f.records, f.at))
                    del files[version]
            yield pd.DataFrame(done, columns=["path", "version", "records", "bytes"])
        for f in files.values():
            f.out.close()
        yield pd.DataFrame([(f.path, f.version, f.records, f.at) for f in files.values()], columns=["path", "version", "records", "bytes"])

    pages = pages.select(pages["page_id"].cast("string"), pages["url"], pages["html"])
    return materialize(pages.mapInPandas(run, "path string, version int, records long, bytes long"), "arc_manifest")


def arc_fields(body: bytes) -> list[str]:
    """Field names of the header lines, from the version block."""
    version, fields = body.split(b"\n")[:2]
    names = fields.decode().split()
    if version.split()[0] not in (b"1", b"2") or names[-1] != "Archive-length":
        raise ValueError(f"ARC version block not understood: {body[:80]!r}")
    return names


def arc_meta(head: bytes, names: list[str]) -> dict:
    """One header line by the declared fields; an URL with spaces keeps them."""
    parts = head.rstrip(b"\n").rsplit(b" ", len(names) - 1)
    if len(parts) != len(names):
        raise ValueError(f"ARC header with {len(parts)} of {len(names)} fields: {head[:80]!r}")
    return {k: v.decode("utf-8", "replace") for k, v in zip(names, parts)}


def member_at(stream, at: int) -> tuple[bytes, int]:
    """The gzip member that starts at ``at`` and where the next one does."""
    stream.seek(at)
    z, out, read = zlib.decompressobj(31), [], 0
    while not z.eof:
        piece = stream.read(1 << 16)
        if not piece:
            raise ValueError(f"gzip member at {at} is cut short")
        read += len(piece)
        out.append(z.decompress(piece))
    return b"".join(out), at + read - len(z.unused_data)


def plain_at(stream, at: int) -> tuple[bytes, bytes, bytes]:
    stream.seek(at)
    head = stream.readline()
    return head, b"\n", stream.read(int(head.split()[-1]))


def arc_records(path: str) -> Iterator[tuple[int, dict, bytes]]:
    """(offset, header fields, block) of each record after the version block, of a plain or a gzipped ARC file."""
    with _open(path) as f:
        packed = f.peek(2)[:2] == b"\x1f\x8b"
        end = f.seek(0, 2)
        f.seek(0)
        names, at = None, 0
        while at < end:
            if packed:
                data, after = member_at(f, at)
                head, _, rest = data.partition(b"\n")
                size = int(head.split()[-1])
                block, gap = rest[:size], rest[size:]
            else:
                f.seek(at)
                head = f.readline()
                if head == b"\n":
                    at += 1
                    continue
                size = int(head.split()[-1])
                block, gap = f.read(size), b""
                after = f.tell()
            if len(block) != size or gap.strip(b"\n"):
                raise ValueError(f"ARC record at {at} does not have its declared length")
            if names is None:
                if not head.startswith(b"filedesc:"):
                    raise ValueError("not an ARC file")
                names = arc_fields(block)
            else:
                yield at, arc_meta(head, names), block
            at = after


def _open(path: str):
    import io

    fs, inner = _fs(path)
    return io.BufferedReader(fs.open_input_file(inner), 1 << 20)


def http_parts(block: bytes) -> tuple[dict, bytes, bytes]:
    """Lower-case header fields, head bytes, payload."""
    head, gap, payload = block.partition(b"\r\n\r\n")
    fields = dict((k.strip().lower().decode("latin-1"), v.strip().decode("utf-8", "replace")) for k, _, v in (x.partition(b":") for x in head.split(b"\r\n")[1:]))
    return fields, head + gap, payload


def record_id(path: str, at: int) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{path.rsplit('/', 1)[-1]}#{at}')}>"


def iso_date(date14: str) -> str:
    d = (date14 + "00000000000000")[:14] if date14[:8].isdigit() else "19700101000000"
    return datetime.datetime.strptime(d, "%Y%m%d%H%M%S").strftime("%Y-%m-%dT%H:%M:%SZ")


def by_file(rows: DataFrame, files: int) -> DataFrame:
    """A file's rows together; the number is set, for the rows are too few for adaptive execution to see the work."""
    return rows.repartition(max(1, min(files, 20_000)), "path")


def index_arc(manifest: DataFrame) -> DataFrame:
    """One row per ARC record: where it is, what it says, the digest of its payload."""

    def run(batches):
        for rows in batches:
            for path in rows["path"]:
                out = []
                for at, meta, block in arc_records(path):
                    fields, _, payload = http_parts(block)
                    out.append((path, at, meta["URL"], meta["Archive-date"], fields.get("x-page-id"), len(payload), digest32(payload)))
                yield pd.DataFrame(out, columns=["path", "at", "url", "date14", "page", "payload_bytes", "payload_digest"])

    files = by_file(manifest.select("path"), manifest.count())
    out = files.mapInPandas(run, "path string, at long, url string, date14 string, page string, payload_bytes long, payload_digest string")
    return materialize(out.withColumn("page_id", F.col("page").cast("long")).drop("page"), "arc_index")


def resolve(index: DataFrame, least: int = 0) -> DataFrame:
    """``index`` with the record each payload is stored in: the smallest page_id, then file and offset."""
    order = F.struct(F.col("page_id").isNull().alias("last"), "page_id", "path", "at", "url", "date14")
    firsts = index.where(F.col("payload_bytes") >= least).groupBy("payload_digest").agg(F.min(order).alias("first"))
    firsts = materialize(firsts, "warc_firsts")
    return index.join(firsts, "payload_digest", "left")


def warc_record(kind: str, fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = [("WARC-Type", kind), *fields, ("WARC-Block-Digest", "sha1:" + digest32(block)), ("Content-Length", str(len(block)))]
    data = "WARC/1.1\r\n".encode() + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + b"\r\n\r\n"
    return gzip_member(data)


def arc_to_warc(manifest: DataFrame, folder: str, least: int = 0) -> DataFrame:
    """Convert the ARC files of ``manifest``; a WARC file for each, and the manifest of those."""

    def run(batches):
        source = out = None
        path, n = None, 0
        full = ""

        def close():
            source.close()
            out.close()
            return pd.DataFrame([(full, n)], columns=["path", "records"])

        for rows in batches:
            for r in rows.itertuples(index=False):
                if r.path != path:
                    if path is not None:
                        yield close()
                    path, n = r.path, 0
                    source = _open(path)
                    name = f"{path.rsplit('/', 1)[-1].split('.')[0]}-{uuid.uuid4().hex[:8]}.warc.gz"
                    out, full = _create(folder, name)
                    date = iso_date(r.date14)
                    info = f"software: bcfilter\r\nformat: WARC File Format 1.1\r\nconverted-from: {path.rsplit('/', 1)[-1]}\r\n".encode()
                    out.write(warc_record("warcinfo", [("WARC-Record-ID", record_id(path, -1)), ("WARC-Date", date), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")], info))
                head, _, rest = member_at(source, r.at)[0].partition(b"\n") if path.endswith(".gz") else plain_at(source, r.at)
                block = rest[: int(head.split()[-1])]
                _, http, payload = http_parts(block)
                fields = [
                    ("WARC-Record-ID", record_id(path, r.at)), ("WARC-Date", iso_date(r.date14)), ("WARC-Target-URI", r.url),
                    ("WARC-IP-Address", "0.0.0.0"), ("WARC-Payload-Digest", "sha1:" + r.payload_digest), ("Content-Type", "application/http; msgtype=response"),
                ]
                if not isinstance(r.first_path, str) or (r.first_path, r.first_at) == (path, r.at):
                    out.write(warc_record("response", fields, block))
                else:
                    more = [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(r.first_path, int(r.first_at))), ("WARC-Refers-To-Target-URI", r.first_url), ("WARC-Refers-To-Date", iso_date(r.first_date14))]
                    if isinstance(r.first_page, str):
                        more.append(("X-Refers-To-Page-Id", r.first_page))
                    out.write(warc_record("revisit", fields + more, http))
                n += 1
        if path is not None:
            yield close()

    rows = resolve(index_arc(manifest), least).select(
        "path", "at", "url", "date14", "payload_digest", F.col("first.path").alias("first_path"), F.col("first.at").alias("first_at"),
        F.col("first.url").alias("first_url"), F.col("first.date14").alias("first_date14"), F.col("first.page_id").cast("string").alias("first_page"),
    )
    rows = by_file(rows, manifest.count()).sortWithinPartitions("path", "at")
    return materialize(rows.mapInPandas(run, "path string, records long"), "warc_manifest")


def warc_records(path: str) -> Iterator[tuple[dict, bytes]]:
    """Header fields (lower case) and block of each record of a gzipped WARC file, one after the other."""
    import gzip

    with _open(path) as raw, gzip.GzipFile(fileobj=raw) as f:
        while head := f.readline():
            if head.strip() == b"":
                continue
            if not head.startswith(b"WARC/"):
                raise ValueError(f"no WARC record: {head[:40]!r}")
            fields = {}
            while (line := f.readline()).strip():
                k, _, v = line.decode("utf-8", "replace").partition(":")
                fields[k.strip().lower()] = v.strip()
            block = f.read(int(fields["content-length"]))
            if (want := fields.get("warc-block-digest")) and want != "sha1:" + digest32(block):
                raise ValueError(f"block of {fields.get('warc-record-id')} does not match its digest")
            yield fields, block


def read_warc(manifest: DataFrame) -> DataFrame:
    """All records but ``warcinfo``: identifiers, type, digest, headers and, for responses, the payload."""

    def run(batches):
        names = ["record_id", "record_type", "url", "date", "payload_digest", "page_id", "payload_bytes", "refers_to", "payload"]
        for rows in batches:
            for path in rows["path"]:
                out = []
                for fields, block in warc_records(path):
                    if fields["warc-type"] == "warcinfo":
                        continue
                    http, _, payload = http_parts(block)
                    kept = payload if fields["warc-type"] == "response" else None
                    digest = fields["warc-payload-digest"].removeprefix("sha1:")
                    if kept is not None and digest32(kept) != digest:
                        raise ValueError(f"payload of {fields['warc-record-id']} does not match its digest")
                    out.append((fields["warc-record-id"], fields["warc-type"], fields["warc-target-uri"], fields["warc-date"], digest, http.get("x-page-id"), http.get("content-length"), fields.get("x-refers-to-page-id"), kept))
                    if len(out) >= 256:
                        yield pd.DataFrame(out, columns=names)
                        out = []
                yield pd.DataFrame(out, columns=names)

    files = by_file(manifest.select("path"), manifest.count())
    rows = files.mapInPandas(run, "record_id string, record_type string, url string, date string, payload_digest string, page_id string, payload_bytes string, refers_to string, payload binary")
    return rows.withColumns({c: F.col(c).cast("long") for c in ("page_id", "payload_bytes", "refers_to")})


def archive_pages(pages: DataFrame, least: int = 0) -> DataFrame:
    """Pages to ARC, ARC to WARC, WARC read back."""
    spark = pages.sparkSession
    arcs = write_arc(pages, new_path(spark, "arc"))
    return read_warc(arc_to_warc(arcs, new_path(spark, "warc"), least))
