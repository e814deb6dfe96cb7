"""WARC archives: a deduplicating writer and a salvage reader.

Writer: one record a page, the payload its UTF-8 html behind an HTTP header. Of pages with equal
payloads of at least ``least`` bytes the one with the largest page_id (then the latest row) is a
``response``, the others are ``revisit`` records that name it and carry the HTTP header only. Each record is
a gzip member of its own. Files are written by Spark's text sink: members are its lines, and its
line separator is an empty gzip member, which readers skip; so any Hadoop file system works and
the committer discards what lost tasks wrote.

Reader: whole files of bounded size are walked member by member (or version line by version line in uncompressed archives), and
members, which may hold any number of records, record by record as they are inflated. A member or record that fails a check (inflation, CRC, header,
length, trailing blank lines, block digest) is quarantined: the reader searches on for the next place where a valid member or version line
begins, goes on from there, and logs the bytes between as a gap, inside a member by inner offsets. Nothing after the damage is lost but what the damaged
member itself holds behind it. Files go through Spark's ``binaryFile``, which refuses those above 2 GB.

A null html is an empty payload; null ids and urls are written as empty values and read back as null.
An empty table writes an archive without records. Repeated rows are records of their own.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_broadcast, keep, lean, scratch, small

VERSION = b"WARC/1.1"
_STARTS = re.compile(rb"^WARC/1\.\d\r?\n", re.M)
#: An empty gzip member; sent as the text sink's line separator in a one-byte encoding.
EMPTY_MEMBER = bytes([0x1F, 0x8B, 8, 0, 0, 0, 0, 0, 0, 3, 3, 0, 0, 0, 0, 0, 0, 0, 0, 0])
MEMBER = b"\x1f\x8b\x08"
#: Bytes of an archive that are inflated at a time.
FEED = 1 << 14
#: Bytes that a record's header takes at most.
HEADER = 1 << 20
#: Bytes of records, before compression, that a written file holds at most (one record at least): the reader takes a file at a time.
ARCHIVE_BYTES = 256 << 20
DATE = "2024-01-01T00:00:00Z"


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record(kind: str, page: int | None, row: int, url: str | None, payload: bytes, digest: str, refers: str | None) -> bytes:
    """One record; a revisit has the HTTP header of the full payload, not the payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if kind == "revisit" else http + payload
    head = [
        ("WARC-Type", kind), ("WARC-Record-ID", f"<urn:page:{'' if page is None else page}:{row}>"), ("WARC-Date", DATE),
        ("WARC-Target-URI", (url or "").replace("\r", "").replace("\n", "")), ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("WARC-Block-Digest", f"sha1:{sha1_base32(block)}"), ("Content-Type", "application/http; msgtype=response"),
    ]
    if refers is not None:
        head += [("WARC-Refers-To", f"<urn:page:{refers}>"), ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")]
    head.append(("Content-Length", str(len(block))))
    return VERSION + b"\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + b"\r\n\r\n"


def member(data: bytes, level: int = 3) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def plan_records(pages: DataFrame, least: int = 0) -> DataFrame:
    """Adds to page_id, url, html: row id, digest of the payload, and for revisits the record they refer to."""
    rows = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"),
        F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary").alias("payload"),
    ).withColumn("row", F.monotonically_increasing_id()).withColumn("sha", F.sha1("payload"))
    best = F.max(F.struct("page_id", "row"))
    copies = rows.where(F.octet_length("payload") >= least).groupBy("sha").agg(best.alias("best"), F.count(F.lit(1)).alias("n")).where("n > 1").select("sha", "best")
    copies = bounded_broadcast(keep(copies, "copies"), 100_000)
    joined = rows.join(copies, "sha", "left")
    again = (F.octet_length("payload") >= least) & F.col("best").isNotNull() & (F.col("best.row") != F.col("row"))
    refers = F.concat_ws(":", F.coalesce(F.col("best.page_id").cast("string"), F.lit("")), F.col("best.row").cast("string"))
    return joined.select("page_id", "row", "url", "payload", F.when(again, refers).alias("refers"))


def write_archive(pages: DataFrame, path: str, least: int = 0, records_per_file: int = 20_000, archive_bytes: int = ARCHIVE_BYTES) -> None:
    """Writes ``pages`` (page_id, url, html) as gzipped WARC files under ``path``.

    A file holds at most ``records_per_file`` records, and so few that they stay within ``archive_bytes`` even if all are as long as the longest.
    """
    most = pages.agg(F.max(F.octet_length(F.col("html").cast("string")) + 2 * F.coalesce(F.octet_length(F.col("url").cast("string")), F.lit(0)))).first()[0] or 0
    records_per_file = max(1, min(records_per_file, archive_bytes // (most + 2048)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            out = []
            for page, row, url, payload, refers in zip(*(c.to_pylist() for c in b.columns), strict=True):
                out.append(member(record("response" if refers is None else "revisit", page, row, url, payload, sha1_base32(payload), refers)))
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["member"])

    made = plan_records(pages, least).mapInArrow(lean(run), "member binary")
    (made.select(F.col("member").cast("string").alias("value")).write.option("maxRecordsPerFile", records_per_file)
     .option("encoding", "ISO-8859-1").option("lineSep", EMPTY_MEMBER.decode("latin-1")).text(path))


def _headers(data: bytes, at: int) -> tuple[dict[str, str], int] | None:
    """Headers of the record whose version line is at ``at``, and where its block begins."""
    stop = data.find(b"\r\n\r\n", at)
    if stop < 0:
        return None
    lines = data[at:stop].split(b"\r\n")
    if not re.fullmatch(rb"WARC/1\.\d", lines[0]):
        return None
    out = {}
    for x in lines[1:]:
        k, colon, v = x.partition(b":")
        if not colon:
            return None
        out[k.decode("latin-1").strip().lower()] = v.decode("utf-8", "replace").strip()
    return out, stop + 4


def read_record(data: bytes, at: int) -> tuple[dict[str, str], bytes, int] | str:
    """(headers, block, end) of the record at ``at``, or what is wrong with it."""
    found = _headers(data, at)
    if not found:
        return "header"
    head, begin = found
    if not re.fullmatch(r"\d{1,18}", head.get("content-length", "")):
        return "length"
    end = begin + int(head["content-length"])
    if data[end : end + 4] != b"\r\n\r\n":
        return "end of record"
    block = data[begin:end]
    said = head.get("warc-block-digest", "")
    if said.startswith("sha1:") and said[5:] != sha1_base32(block):
        return "block digest"
    return head, block, end + 4


class RecordWalk:
    """Walks records whose bytes come in pieces; holds no more than the record that is not whole yet.

    ``feed`` gives ("record", begin, end, headers, block) and ("gap", begin, end, reason, None), in order, by offsets in all bytes fed.
    """

    def __init__(self):
        self.held, self.base, self.bad, self.reason = b"", 0, -1, ""

    def _short(self) -> bool:
        """Whether the record that ``held`` begins with may still become whole."""
        found = _headers(self.held, 0)
        if not found:
            return b"\r\n\r\n" not in self.held and len(self.held) < HEADER and (self.held.startswith(VERSION[:7]) or VERSION.startswith(self.held))
        size = found[0].get("content-length", "")
        return bool(re.fullmatch(r"\d{1,18}", size)) and len(self.held) < found[1] + int(size) + 4

    def feed(self, more: bytes, last: bool = False) -> Iterator[tuple]:
        self.held += more
        while self.held and (last or not self._short()):
            got = read_record(self.held, 0)
            if not isinstance(got, str):
                if self.bad >= 0:
                    yield "gap", self.bad, self.base, self.reason, None
                    self.bad = -1
                yield "record", self.base, self.base + got[2], got[0], got[1]
                self._drop(got[2])
                continue
            if self.bad < 0:
                self.bad, self.reason = self.base, got
            found = _STARTS.search(self.held, 1)
            if found:
                self._drop(found.start())
            else:  # the last bytes may be the beginning of a version line
                self._drop(len(self.held) if last else max(1, len(self.held) - len(VERSION)))
                if not last and not self.held.startswith(b"W"):
                    at = self.held.find(b"W")
                    self._drop(at if at >= 0 else len(self.held))
        if last and self.bad >= 0:
            yield "gap", self.bad, self.base, self.reason, None

    def _drop(self, n: int) -> None:
        self.held, self.base = self.held[n:], self.base + n


def _inflated(data: bytes, at: int) -> Iterator[tuple[bytes, int]]:
    """(bytes, where the member at ``at`` ends, 0 until that is known) piece by piece; fails on damage, also on a cut."""
    z, seen = zlib.decompressobj(31), at
    while not z.eof:
        if seen >= len(data):
            raise zlib.error("cut")
        before = z.copy()
        try:
            piece = z.decompress(data[seen : seen + FEED])
        except zlib.error:  # what stands before the damage, byte by byte
            for i in range(seen, min(seen + FEED, len(data))):
                yield before.decompress(data[i : i + 1]), 0
            raise
        seen += min(FEED, len(data) - seen)
        yield piece, seen - len(z.unused_data) if z.eof else 0


def _member_end(data: bytes, at: int) -> tuple[int, str]:
    """Where the gzip member at ``at`` ends, or -1 and what is wrong with it; nothing of it is held."""
    end = -1
    try:
        for _, end in _inflated(data, at):  # noqa: B007
            pass
    except zlib.error as e:
        return -1, "cut member" if str(e) == "cut" else "member"
    return end, ""


def _of_member(data: bytes, at: int, sound: bool) -> Iterator[tuple]:
    """What the member at ``at`` holds; of one that is not sound only records whose stated block digest is right."""
    walk = RecordWalk()
    try:
        for piece, _ in _inflated(data, at):
            for x in walk.feed(piece):
                if sound or x[0] == "record" and x[3].get("warc-block-digest", "").startswith("sha1:"):
                    yield x
        yield from walk.feed(b"", True) if sound else ()
    except zlib.error:
        return


def salvage(data: bytes) -> Iterator[tuple]:
    """("record", begin, end, headers, block, inner) and ("gap", begin, end, reason, None, inner) of an archive's bytes.

    Gzipped members, of one record or many, and plain records may all occur. ``inner`` is None for plain records and for gaps of the archive itself. For
    what stands in a member begin and end are the member's, and ``inner`` the offsets in its inflated bytes. A member that is not sound is a gap
    from where it begins to the next valid member or version line; whole records before the damage are recovered where their block digest is right, with
    begin and end both at the member's beginning. Gaps and members leave no byte out but those of empty members.
    """
    at, bad, reason = 0, -1, ""
    while at < len(data):
        why, stop = "no member or version line", -1
        if data.startswith(MEMBER, at):
            stop, why = _member_end(data, at)
            if stop >= 0 and bad >= 0:
                yield "gap", bad, at, reason, None, None
                bad = -1
            for what, a, b, x, block in _of_member(data, at, stop >= 0):
                yield what, at, max(stop, at), x, block, (a, b)
        elif data.startswith(b"WARC/", at):
            got = read_record(data, at)
            if isinstance(got, str):
                why = got
            else:
                if bad >= 0:
                    yield "gap", bad, at, reason, None, None
                    bad = -1
                stop = got[2]
                yield "record", at, stop, got[0], got[1], None
        if stop >= 0:
            at = stop
            continue
        if bad < 0:
            bad, reason = at, why
        a = data.find(MEMBER, at + 1)
        m = _STARTS.search(data, at + 1)
        places = [x for x in (a, m.start() if m else -1) if x >= 0]
        at = min(places, default=len(data))
    if bad >= 0:
        yield "gap", bad, len(data), reason, None, None


READ_SCHEMA = (
    "file string, kind string, begin long, end long, inner_begin long, inner_end long, reason string, record_type string, record_id string, target_uri string, "
    "refers_to string, payload_digest string, payload_bytes long, digest_ok boolean, payload binary"
)


def read_archives(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """Records and quarantined gaps of all archives under ``path``; see READ_SCHEMA.

    Digest and length are of the full payload: worked out from it for a response, as stated for a revisit.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in READ_SCHEMA.split(", ")]
        kinds = [pa.string(), pa.string(), *[pa.int64()] * 4, *[pa.string()] * 6, pa.int64(), pa.bool_(), pa.binary()]

        def pack(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kinds[i]) for i in range(len(kinds))], names)

        for b in batches:
            for file, data in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                rows, held = [], 0
                for what, begin, end, head, block, inner in salvage(data.as_py()):
                    a, z = inner or (None, None)
                    if what == "gap":
                        rows.append((file, what, begin, end, a, z, head, *[None] * 8))
                    else:
                        http, _, payload = block.partition(b"\r\n\r\n")
                        said = head.get("warc-payload-digest", "").removeprefix("sha1:")
                        if head.get("warc-type") == "revisit":
                            size = re.search(rb"(?im)^content-length: *(\d+)", http)
                            size, digest, ok, payload = int(size[1]) if size else None, said, None, None
                        else:
                            size, digest = len(payload), sha1_base32(payload)
                            ok = digest == said
                        rows.append((file, what, begin, end, a, z, None, head.get("warc-type"), head.get("warc-record-id"), head.get("warc-target-uri"), head.get("warc-refers-to"), digest, size, ok, payload if with_payload else None))
                        held += len(payload or b"") if with_payload else 100
                    if held > 4 << 20:
                        yield pack(rows)
                        rows, held = [], 0
                yield pack(rows)

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "content")
    return files.mapInArrow(lean(run), READ_SCHEMA)


def page_of(column: str) -> Column:
    """The page_id in a record id that this module's writer made."""
    return F.nullif(F.regexp_extract(column, r"^<urn:page:(-?\d*):", 1), F.lit("")).cast("long")


def archive_and_read(pages: DataFrame, least: int = 0) -> DataFrame:
    """Writes the pages to the shared folder, reads the archives back; one row per record."""
    path = scratch(pages.sparkSession, "warc")
    write_archive(pages, path, least)
    return read_archives(pages.sparkSession, path, with_payload=False).where("kind = 'record'").select(
        page_of("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type",
        F.when(F.col("record_type") == "revisit", page_of("refers_to")).alias("refers_to"), "digest_ok",
    )
