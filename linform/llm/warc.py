"""WARC archives: a writer with revisit records, and a reader that salvages what is left of damaged files.

The writer's tasks write archives of their own in the shared folder (one gzip member a record, files turned
over at a size), under names that no other attempt has, and return a list of them; only files that a finished
task lists are ever read, so a lost executor or a second attempt leaves nothing but unread files.

The reader checks each member and record (gzip checksum, version line, headers, length, block digest). After a
check fails it searches on for the next gzip member or version line at which a record can be read, goes on from
there, and logs the bytes between as a gap; gaps are rows beside the records, with their reason. Damage inside a
member of several records costs the damaged records only: the inflated bytes are searched on for the next version
line, and of a member that is cut off or broken what can be inflated is read. A record without a block digest counts
in sound members only. Members are inflated through a window, so a record has to fit in memory, a member need not.

Rows of a file cover it: [start, end) is the region of the file, a member, a plain record or a gap; inner_start and
inner_end are places among the inflated bytes of the member, for its records and for gaps between them.

Of records with equal payloads of at least `least_bytes` bytes, the one of the largest page_id is a response and
the others revisit it. Null payloads count as empty; a null page_id ranks lowest (and revisits, where an equal
payload has an id; if none has, all are responses, refers_to null). Rows that repeat the winning page_id with an
equal payload are all responses. Null URLs leave their header out. An empty table writes no archive. Extra
columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linform.llm.common import materialise, new_path, redealt

# The format's version line and names.
VERSION, DATE = b"WARC/1.1\r\n", "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MAGIC = b"\x1f\x8b\x08"
#: Bytes after which a task begins another archive; bytes read at a time; bytes in which a header is first sought.
TURN_OVER, STEP, HEADER = 64 << 20, 1 << 20, 1 << 16
#: Inflated bytes of a member up to which they are kept from the pass that checks it; longer ones are inflated again.
KEEP = 16 << 20


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(page_id: int | None) -> str:
    return f"<urn:x-page:{'none' if page_id is None else page_id}>"


def page_of(urn: str | None) -> int | None:
    found = re.fullmatch(r"<urn:x-page:(-?\d+)>", urn or "")
    return int(found[1]) if found else None


def build_record(page_id: int | None, url: str | None, payload: bytes, revisit: bool, refers_to: int | None) -> bytes:
    """One record; a revisit holds the response's headers only."""
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode() + (b"" if revisit else payload)
    head = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", record_id(page_id)), ("WARC-Date", DATE)]
    if url is not None:
        head.append(("WARC-Target-URI", re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)))
    head.append(("WARC-Payload-Digest", f"sha1:{sha1_base32(payload)}"))
    if revisit:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to))]
    head += [("WARC-Block-Digest", f"sha1:{sha1_base32(block)}"), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    return VERSION + "".join(f"{k}: {v}\r\n" for k, v in head).encode("utf-8", "surrogatepass") + b"\r\n" + block + b"\r\n\r\n"


class Bytes:
    """Random reads of a file through one window."""

    def __init__(self, file, size: int):
        self.file, self.size, self.at, self.window = file, size, 0, b""

    def read(self, at: int, n: int = STEP) -> bytes:
        n = max(0, min(n, self.size - at))
        if not (self.at <= at and at + n <= self.at + len(self.window)):
            self.file.seek(at)
            self.at, self.window = at, self.file.read(min(max(n, STEP), self.size - at))
        return self.window[at - self.at : at - self.at + n]

    def find(self, what: bytes, at: int) -> int:
        """The first place of what at or after `at`; the size if there is none."""
        while at < self.size:
            found = self.read(at).find(what)
            if found >= 0:
                return at + found
            at += max(1, min(STEP, self.size - at) - len(what) + 1)
        return self.size


class Damage(Exception):
    pass


class Inflated:
    """A gzip member at a place, inflated forwards through a window. `end`: where it ends, or where it can be inflated
    no further; `fault`: why it cannot, None for a sound member."""

    def __init__(self, data: Bytes, at: int, limit: int | None = None):
        self.data, self.begin, self.limit = data, at, data.size if limit is None else limit
        self._rewind()
        kept, size = [], 0
        while part := self._more():
            size += len(part)
            kept = [*kept, part] if size <= KEEP else []
        self.size, self.end, self.fault = size, self.place, self.reason
        self._rewind()
        if size <= KEEP:
            self.window, self.done = b"".join(kept), True

    def _rewind(self) -> None:
        self.tool, self.place, self.reason, self.done = zlib.decompressobj(31), self.begin, None, False
        self.low, self.window = 0, b""

    def _more(self) -> bytes:
        """The next inflated bytes; none at the end."""
        while not self.done:
            part = self.data.read(self.place, min(1 << 16, self.limit - self.place))
            if not part:
                self.reason, self.done = "cut off member", True
                return b""
            out = self._feed(part)
            if out:
                return out
        return b""

    def _feed(self, part: bytes) -> bytes:
        """Inflate some bytes; if they are broken, as many as are not, found by halves."""
        held = self.tool.copy()
        try:
            out = self.tool.decompress(part)
            self.place += len(part) - len(self.tool.unused_data)
            self.done = self.tool.eof
            return out
        except zlib.error:
            self.tool = held
            if len(part) == 1:
                self.reason, self.done = "broken member", True
                return b""
            out = self._feed(part[: len(part) // 2])
            return out if self.done else out + self._feed(part[len(part) // 2 :])

    def read(self, at: int, n: int) -> bytes:
        """Inflated bytes; what lies before a place that was asked for may be gone, and is then inflated again."""
        if at < self.low:
            self._rewind()
        while self.low + len(self.window) < at + n and not self.done:
            if at - self.low > STEP:
                skip = min(at - self.low, len(self.window))
                self.low, self.window = self.low + skip, self.window[skip:]
            more = self._more()
            self.window += more
        return self.window[at - self.low : at - self.low + n]

    def find(self, what: bytes, at: int) -> int:
        """The first place of what at or after `at`; the size if there is none."""
        while at < self.size:
            part = self.read(at, STEP)
            found = part.find(what)
            if found >= 0:
                return at + found
            at += max(1, len(part) - len(what) + 1)
        return self.size

    def rows(self) -> Iterator[tuple]:
        """("record", start, end, headers, block) and ("gap", start, end, reason) of the inflated bytes, in order."""
        at, lost, reason = 0, None, ""
        while at < self.size:
            try:
                headers, block, end = _record(self.read, at)
                if self.fault and not headers.get("warc-block-digest", "").startswith("sha1:"):
                    raise Damage(self.fault)
            except Damage as e:
                if lost is None:
                    lost, reason = at, str(e)
                at = self.find(b"WARC/", at + 1)
                continue
            if lost is not None:
                yield "gap", lost, at, reason
                lost = None
            yield "record", at, end, headers, block
            at = end
        if lost is not None:
            yield "gap", lost, self.size, reason


def _parse(head: bytes) -> dict[str, str]:
    out = {}
    for line in head.split(b"\r\n")[1:]:
        name, colon, value = line.decode("utf-8", "replace").partition(":")
        if not colon:
            raise Damage("broken header")
        out[name.strip().lower()] = value.strip()
    if not {"warc-type", "warc-record-id", "warc-date"} <= out.keys():
        raise Damage("missing header")
    return out


def _record(take, at: int) -> tuple[dict[str, str], bytes, int]:
    """Headers, block and end of the record at a place. take(place, n): bytes there."""
    n, end = HEADER, -1
    while end < 0:
        head = take(at, n)
        if not re.match(rb"WARC/\d\.\d\r\n", head):
            raise Damage("no version line")
        end = head.find(b"\r\n\r\n")
        if end < 0 and len(head) < n:
            raise Damage("no end of header")
        n *= 2
    headers = _parse(head[:end])
    if not re.fullmatch(r"\d+", headers.get("content-length", "")):
        raise Damage("no length")
    n, start = int(headers["content-length"]), at + end + 4
    block = take(start, n + 4)
    if len(block) != n + 4 or block[n:] != b"\r\n\r\n":
        raise Damage("wrong length")
    block = block[:n]
    told = headers.get("warc-block-digest", "")
    if told.startswith("sha1:") and told[5:] != sha1_base32(block):
        raise Damage("wrong digest")
    return headers, block, start + n + 4


def _parts(data: Bytes, at: int) -> tuple[Inflated | None, Iterator[tuple], int]:
    """What begins at a place, if a record can be read of it: the member (None for a plain record), its rows (the
    first record among them is read by now), and where it ends."""
    if data.read(at, 3) != MAGIC:
        headers, block, end = _record(data.read, at)
        return None, iter([("record", None, None, headers, block)]), end
    member, first = Inflated(data, at), []
    rows = member.rows()
    for row in rows:
        first.append(row)
        if row[0] == "record":
            return member, chain(first, rows), member.end
    raise Damage(member.fault or (first[0][3] if first else "empty member"))


def salvage(file, size: int) -> Iterator[tuple]:
    """("record", start, end, inner_start, inner_end, headers, block) and ("gap", start, end, inner_start, inner_end,
    reason) of an archive, in order.

    Takes gzip members (of a record or more each) and plain records. The regions [start, end) add up to the file.
    """
    data = Bytes(file, size)
    at, lost, reason, found = 0, None, "", None
    ahead = {MAGIC: -1, b"WARC/": -1}  # next places of what can begin a record

    def after(place: int) -> int:
        for what, known in ahead.items():
            ahead[what] = data.find(what, place + 1) if known <= place else known
        return min(ahead.values())

    while at < size:
        try:
            member, rows, end = found or _parts(data, at)
        except Damage as e:
            if lost is None:
                lost, reason = at, str(e)
            at = after(at)
            continue
        found = None
        if lost is not None:
            yield "gap", lost, at, None, None, reason
            lost = None
        begin, at, broken = at, end, member is not None and member.fault is not None
        if broken:  # the next record may begin before the place where inflating failed
            at = after(begin)
            while at < size:
                try:
                    found = _parts(data, at)
                    break
                except Damage:
                    at = after(at)
            if at < end:  # what was inflated beyond is not of this member
                member = Inflated(data, begin, at)
                rows, end, broken = member.rows(), at, member.fault is not None
        for kind, a, b, *rest in rows:
            yield kind, begin, end, a, b, *rest
        if broken and end < at:
            yield "gap", end, at, None, None, member.fault
        elif broken:
            yield "gap", begin, end, member.size, None, member.fault
    if lost is not None:
        yield "gap", lost, size, None, None, reason


def payload_of(headers: dict[str, str], block: bytes) -> tuple[int, str, bytes]:
    """Bytes and digest of the full payload, and what of it the record holds."""
    http, _, body = block.partition(b"\r\n\r\n")
    told = headers.get("warc-payload-digest", "").removeprefix("sha1:")
    if headers.get("warc-type") == "revisit":
        length = re.search(rb"(?im)^content-length:\s*(\d+)", http)
        return int(length[1]) if length else 0, told, b""
    return len(body), sha1_base32(body), body


def _open(path: str):
    return fs.FileSystem.from_uri(re.sub(r"^s3[an]:", "s3:", path))


def assign_records(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """(page_id, url, html) -> those and (revisit, refers_to)."""
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html")).withColumn("sum", F.unhex(F.sha2("html", 256)))
    keys = pages.where(F.octet_length("html") >= least_bytes).select("page_id", "sum")
    groups = keys.groupBy("sum").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1 and refers_to is not null").drop("n")
    others = keys.join(redealt(groups, "sum"), "sum").where(~F.col("page_id").eqNullSafe(F.col("refers_to"))).distinct()
    others = others.select(F.coalesce("page_id", F.lit(-(2**63))).alias("kid"), F.col("sum"), "refers_to")
    joined = pages.withColumn("kid", F.coalesce("page_id", F.lit(-(2**63)))).join(others, ["kid", "sum"], "left")
    return joined.select("page_id", "url", "html", F.col("refers_to").isNotNull().alias("revisit"), "refers_to")


def write_archives(records: DataFrame, folder: str, turn_over: int = TURN_OVER) -> DataFrame:
    """Write (page_id, url, html, revisit, refers_to) and return the list (path, bytes, records) as a written table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _open(folder)
        store.create_dir(root, recursive=True)
        name, out, size, n = "", None, 0, 0
        for batch in batches:
            for page_id, url, html, revisit, refers_to in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if out is None:
                    name, size, n = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                    out = store.open_output_stream(f"{root}/{name}", compression=None)
                tool = zlib.compressobj(6, zlib.DEFLATED, 31)
                member = tool.compress(build_record(page_id, url, html.encode("utf-8", "surrogatepass"), revisit, refers_to)) + tool.flush()
                out.write(member)
                size, n = size + len(member), n + 1
                if size >= turn_over:
                    out.close()
                    out = None
                    yield listed(name, size, n)
        if out is not None:
            out.close()
            yield listed(name, size, n)

    def listed(name: str, size: int, n: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_pydict({"path": [f"{folder}/{name}"], "bytes": pa.array([size], pa.int64()), "records": pa.array([n], pa.int64())})

    return materialise(records.select("page_id", "url", "html", "revisit", "refers_to").mapInArrow(run, "path string, bytes long, records long"), "archives")


READ = "path string, kind string, start long, end long, inner_start long, inner_end long, reason string, page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def read_archives(listed: DataFrame, payloads: bool = False) -> DataFrame:
    """(path, ...) -> a row for each record and gap of the archives, as READ; payload null unless asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split(" ")[0] for x in READ.split(", ")]
        kinds = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[x.split(" ")[1]] for x in READ.split(", ")]

        def told(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

        for batch in batches:
            for path in batch.column(0).to_pylist():
                store, place = _open(path)
                rows, held = [], 0
                with store.open_input_file(place) as file:
                    for kind, *region in salvage(file, file.size()):
                        region, rest = region[:4], region[4:]
                        if kind == "gap":
                            rows.append((path, kind, *region, rest[0], *[None] * 7))
                        else:
                            headers, block = rest
                            n, digest, body = payload_of(headers, block)
                            rows.append((path, kind, *region, None, page_of(headers.get("warc-record-id")), headers.get("warc-target-uri"), headers.get("warc-type"), page_of(headers.get("warc-refers-to")), n, digest, body if payloads else None))
                            held += len(body) if payloads else 0
                        if len(rows) >= 2_000 or held > 16 << 20:
                            yield told(rows)
                            rows, held = [], 0
                if rows:
                    yield told(rows)

    return listed.select("path").mapInArrow(run, READ)


def archive_pages(spark: SparkSession, pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Write all pages as archives in the shared folder and read them back, about an archive in each task."""
    return read_archives(spread(write_archives(assign_records(pages, least_bytes), new_path(spark, "warc"))))


def spread(listed: DataFrame, share: int = TURN_OVER // 4) -> DataFrame:
    """The list dealt evenly over tasks: one for each `share` bytes, and no fewer than can run at once, but no more
    than there are archives."""
    n, size = listed.agg(F.count("*"), F.sum("bytes")).first()
    tasks = max(1, min(n, max(-(-(size or 0) // share), listed.sparkSession.sparkContext.defaultParallelism)))
    return listed.repartition(tasks)
