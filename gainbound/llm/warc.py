"""WARC archives of pages: writing with revisits, reading, and assembly of captures.

Each page is a capture of three records: a response (or a revisit of an equal payload), its request
and its metadata, which name it by their concurrent-to identifiers. Tasks write gzip-per-record
archives to the shared folder and hand on only the archives' paths, so an archive of a lost or repeated
attempt is never read. Reading streams record by record. Assembly brings the records of a
capture together by those identifiers, in one shuffle, as one nested row.

Of records with equal payloads of at least `least` bytes the one with the largest page_id is the response.

Every row is a capture of its own: rows that repeat a page_id and payload (or have no page_id) are told apart by a number. If
several rows have the largest page_id of a payload, all of them are responses and the others revisit the first.

Edge cases: a null html is an empty payload, a null url an empty target. page_id is an integer. A capture of which a record is
missing has null there. Extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import gzip
import hashlib
import uuid
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
import pyarrow.fs as fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainbound.llm.common import integer_id, settle, shared_uri, small_join

#: An archive is closed once it holds so many bytes.
ARCHIVE_BYTES = 64 << 20
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def base32_of_hex(digest):
    """Upper-case base32 of a column of 40 hex digits: five of them are four base32 digits."""
    parts = [F.lpad(F.conv(F.substring(digest, 5 * i + 1, 5), 16, 32), 4, "0") for i in range(8)]
    return F.translate(F.upper(F.concat(*parts)), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def _identifier(*parts) -> str:
    return uuid.UUID(bytes=hashlib.md5("|".join(map(str, parts)).encode()).digest(), version=4).urn


def _record(kind: str, identifier: str, headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{identifier}>", f"WARC-Date: {DATE}", *(f"{k}: {v}" for k, v in headers), f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(lines).encode() + block + b"\r\n\r\n"


def capture_records(page, url: str | None, payload: bytes, digest: str, refers, nth: int = 0) -> list[bytes]:
    """The records of one page; refers: the page of the response that it revisits, or None; nth: tells rows of one page and payload apart."""
    target = "".join((url or "").split())
    own = _identifier("capture", page, digest, nth)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    about = [("WARC-Target-URI", target), ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    if refers is None:
        main = _record("response", own, about, http + payload)
    else:
        main = _record("revisit", own, [*about, ("WARC-Profile", PROFILE), ("WARC-Refers-To", f"<{_identifier('capture', refers, digest, 0)}>")], http)
    try:
        place = urlsplit(target)
        host, path = place.netloc, (place.path or "/") + (f"?{place.query}" if place.query else "")
    except ValueError:
        host, path = "", "/"
    with_main = [("WARC-Target-URI", target), ("WARC-Concurrent-To", f"<{own}>")]
    request = _record("request", _identifier("request", page, digest, nth), [*with_main, ("Content-Type", "application/http; msgtype=request")], f"GET {path} HTTP/1.1\r\nHost: {host}\r\n\r\n".encode())
    fields = f"page-id: {'' if page is None else page}\r\n".encode()
    return [main, request, _record("metadata", _identifier("metadata", page, digest, nth), [*with_main, ("Content-Type", "application/warc-fields")], fields)]


def _numbered(keyed: DataFrame, twice: DataFrame) -> DataFrame:
    """keyed with `nth`: 0 for one row of each (digest, page_id), other numbers for the rest. twice: those that several rows have.

    Only rows that are repeated are settled and numbered, each by itself, so a pair that very many rows have is never gathered."""
    twice = settle(twice.withColumn("again", F.lit(True)))
    n = twice.count()
    if not n:
        return keyed.withColumn("nth", F.lit(0).cast("long"))

    def look_up(left: DataFrame, right: DataFrame, column: str) -> DataFrame:
        other = right.toDF("_digest", "_page", column)
        return small_join(left, other, (F.col("digest") == F.col("_digest")) & F.col("page_id").eqNullSafe(F.col("_page")), "left", n, 64).drop("_digest", "_page")

    marked = look_up(keyed, twice, "again")
    again = settle(marked.where("again").drop("again").withColumn("_row", F.monotonically_increasing_id()))
    first = settle(again.groupBy("digest", "page_id").agg(F.min("_row").alias("_first")))
    nth = F.when(F.col("_row") == F.col("_first"), 0).otherwise(F.col("_row") + 1).cast("long")
    numbered = look_up(again, first, "_first").withColumn("nth", nth).drop("_row", "_first")
    return marked.where("again is null").drop("again").withColumn("nth", F.lit(0).cast("long")).unionByName(numbered)


def write_archives(pages: DataFrame, least: int = 0, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Archives of pages (page_id, url, html) in the shared folder; returns their paths and sizes, settled."""
    folder = f"{shared_uri(pages.sparkSession)}/warc-{uuid.uuid4().hex}"
    integer_id(pages, "page_id")
    keyed = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("payload")).withColumn("digest", base32_of_hex(F.sha1("payload")))
    alike = settle(keyed.select("digest", "page_id", F.octet_length("payload").alias("bytes")).groupBy("digest", "page_id", "bytes").agg(F.count("*").alias("n")))
    groups = settle(alike.where(F.col("bytes") >= least).groupBy("digest").agg(F.max("page_id").alias("holder"), F.sum("n").alias("n")).where("n > 1").select("digest", "holder"))
    told = small_join(_numbered(keyed, alike.where("n > 1").select("digest", "page_id")), groups, "digest", "left", groups.count(), 48)
    told = told.withColumn("refers", F.when((F.col("holder") != F.col("page_id")) | F.col("page_id").isNull(), F.col("holder"))).select("page_id", "url", "payload", "digest", "refers", "nth")

    def run(batches):
        system, root = fs.FileSystem.from_uri(folder)
        system.create_dir(root, recursive=True)
        out, name, size, n = None, "", 0, 0
        done: list[tuple[str, int, int]] = []
        for batch in batches:
            for page, url, payload, digest, refers, nth in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if out is None:
                    name, size, n = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                    out = system.open_output_stream(f"{root}/{name}", compression=None)
                for record in capture_records(page, url, payload, digest, refers, nth):
                    member = gzip.compress(record, 6, mtime=0)
                    out.write(member)
                    size, n = size + len(member), n + 1
                if size >= archive_bytes:
                    out.close()
                    done.append((f"{folder}/{name}", n, size))
                    out = None
        if out is not None:
            out.close()
            done.append((f"{folder}/{name}", n, size))
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int64()), pa.array([d[2] for d in done], pa.int64())], names=["path", "records", "bytes"])

    return settle(told.mapInArrow(run, "path string, records long, bytes long"))


def parse(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers (lower-case names) and block of each record of an uncompressed stream."""
    while True:
        line = stream.readline()
        while line in (b"\r\n", b"\n"):
            line = stream.readline()
        if not line:
            return
        if not line.startswith(b"WARC/"):
            raise ValueError("a record doesn't begin with its version")
        headers: dict[str, str] = {}
        for raw in iter(stream.readline, b""):
            text = raw.decode("utf-8", "replace").rstrip("\r\n")
            if not text:
                break
            name, _, value = text.partition(":")
            headers.setdefault(name.strip().lower(), value.strip())
        yield headers, stream.read(int(headers.get("content-length", 0)))


_RECORD = "kind string, record_id string, capture_id string, target string, date string, content_type string, refers_to string, payload_digest string, payload_bytes long, page_id long, payload binary"


def read_records(archives: DataFrame, with_payload: bool = False) -> DataFrame:
    """The records of archives (path). capture_id: the record itself, or the one that it is concurrent to."""
    names = [x.split()[0] for x in _RECORD.split(", ")]
    kinds = pa.schema(list(zip(names, [pa.string()] * 8 + [pa.int64()] * 2 + [pa.binary()], strict=True)))

    def row(headers, block):
        bare = lambda k: headers.get(k, "").strip("<>") or None
        kind = headers.get("warc-type")
        out = dict.fromkeys(names) | {"kind": kind, "record_id": bare("warc-record-id"), "target": headers.get("warc-target-uri"), "date": headers.get("warc-date"), "content_type": headers.get("content-type"), "refers_to": bare("warc-refers-to")}
        out["capture_id"] = bare("warc-concurrent-to") or out["record_id"]
        if kind in ("response", "revisit"):
            out["payload_digest"] = headers.get("warc-payload-digest", "").removeprefix("sha1:") or None
        if kind == "response":
            payload = block.partition(b"\r\n\r\n")[2]
            out |= {"payload_bytes": len(payload), "payload": payload if with_payload else None}
        if kind == "metadata":
            fields = dict(x.partition(b":")[::2] for x in block.splitlines())
            out["page_id"] = int(v) if (v := fields.get(b"page-id", b"").strip()) else None
        return out

    def run(batches):
        for batch in batches:
            for path in batch.column(0).to_pylist():
                system, name = fs.FileSystem.from_uri(path)
                held, weight = [], 0
                with system.open_input_stream(name, compression=None) as raw, gzip.GzipFile(fileobj=raw) as stream:
                    for headers, block in parse(stream):
                        held.append(row(headers, block))
                        weight += 500 + len(block) * with_payload
                        if weight > 4 << 20:
                            yield pa.RecordBatch.from_pylist(held, kinds)
                            held, weight = [], 0
                if held:
                    yield pa.RecordBatch.from_pylist(held, kinds)

    n = max(1, min(archives.count(), 1 << 16))
    return archives.select("path").repartition(n).mapInArrow(run, _RECORD)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: capture_id and the structs main (response or revisit), request and metadata."""

    def of(kinds: list[str], *columns: str):
        return F.first(F.when(F.col("kind").isin(kinds), F.struct("kind", "record_id", "date", *columns)), ignorenulls=True)

    return records.where("capture_id is not null").groupBy("capture_id").agg(
        of(["response", "revisit"], "target", "content_type", "refers_to", "payload_digest", "payload_bytes", "payload").alias("main"),
        of(["request"], "target", "content_type").alias("request"), of(["metadata"], "content_type", "page_id").alias("metadata"),
    )


def resolved(captures: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type and refers_to (a page_id) of each capture with a main record."""
    rows = settle(captures.where("main is not null").select("capture_id", F.col("metadata.page_id").alias("page_id"), F.col("main.kind").alias("record_type"), F.col("main.payload_digest").alias("payload_digest"), F.col("main.payload_bytes").alias("payload_bytes"), F.col("main.refers_to").alias("to")))
    plain, again = rows.where("record_type = 'response'"), rows.where("record_type = 'revisit'")
    holders = again.select(F.col("to").alias("capture_id")).distinct().join(plain.select("capture_id", "page_id", "payload_bytes"), "capture_id")
    holders = holders.select(F.col("capture_id").alias("to"), F.col("page_id").alias("refers_to"), F.col("payload_bytes").alias("bytes"))
    columns = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    found = small_join(again, holders, "to", "left", plain.count(), 80).withColumn("payload_bytes", F.col("bytes"))
    return plain.withColumn("refers_to", F.lit(None).cast("long")).select(*columns).union(found.select(*columns))


def archive_and_read(pages: DataFrame, least: int = 0) -> DataFrame:
    """Writes the pages' archives, reads them back and resolves the captures."""
    return resolved(assemble(read_records(write_archives(pages, least))))
