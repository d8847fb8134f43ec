"""Web archives: a writer of one gzip member a record, and a reader that salvages what it can.

The reader checks each member (gzip CRC, record head, declared length, block digest). After a failed
check it searches for the next member that inflates to a record, or the next version line in plain
archives and inside a member, goes on from there, and logs the bytes between as a quarantined gap with
the reason. Gaps and records together cover each file. Records and gaps inside one member share its
range; of a member that fails half way, what was read before the fault is kept.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import common as C
from vecengine.llm.files import resolve

GZIP = b"\x1f\x8b\x08"
VERSION = re.compile(rb"WARC/\d+\.\d+\r?\n")
END = b"\r\n\r\n"


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


# ---------------------------------------------------------------------- records


@dataclass
class Record:
    headers: dict[str, str]  # by lower-case name
    block: bytes
    begin: int = 0
    end: int = 0

    @property
    def kind(self) -> str:
        return self.headers.get("warc-type", "")

    def http(self) -> tuple[dict[str, str], bytes]:
        """HTTP headers by lower-case name, and the payload; a block that is not HTTP is all payload."""
        if not self.headers.get("content-type", "").startswith("application/http"):
            return {}, self.block
        head, _, body = self.block.partition(END)
        lines = head.decode("utf-8", "replace").split("\r\n")[1:]
        return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}, body


@dataclass
class Gap:
    begin: int
    end: int
    reason: str


def encode(headers: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + head.encode("utf-8") + b"\r\n" + block + END


def member(data: bytes, level: int = 4) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def parse(data: bytes, at: int = 0) -> tuple[Record, int]:
    """The record at a place of plain bytes, and the place after it; ValueError says what fails."""
    m = VERSION.match(data, at)
    if not m:
        raise ValueError("no version line")
    stop = data.find(END, m.end() - 2)
    if stop < 0:
        raise ValueError("record head does not end")
    headers: dict[str, str] = {}
    last = None
    for line in data[m.end() : stop].decode("utf-8", "replace").split("\r\n"):
        if line[:1] in (" ", "\t") and last:  # folded line
            headers[last] += " " + line.strip()
            continue
        name, colon, value = line.partition(":")
        if line and not colon:
            raise ValueError("bad header line")
        if line:
            headers[last := name.strip().lower()] = value.strip()
    try:
        size = int(headers["content-length"])
    except (KeyError, ValueError):
        raise ValueError("no content length") from None
    begin, end = stop + len(END), stop + len(END) + size
    if size < 0 or end > len(data):
        raise ValueError("block is cut short")
    block = data[begin:end]
    declared = headers.get("warc-block-digest", "")
    if declared.startswith("sha1:") and declared[5:].upper() != sha1_base32(block):
        raise ValueError("block digest differs")
    if data[end : end + len(END)] not in (END, b"") and not VERSION.match(data, end):
        raise ValueError("no record end")
    return Record(headers, block, at, end), min(len(data), end + (len(END) if data[end : end + len(END)] == END else 0))


# ----------------------------------------------------------------------- reader


@dataclass
class _Window:
    """A file's bytes from `base` on; grows by reading, forgets what is done."""

    source: object
    base: int = 0
    data: bytearray = field(default_factory=bytearray)
    over: bool = False

    def more(self, n: int = 1 << 20) -> bool:
        if not self.over:
            part = self.source.read(n)
            self.over = not part
            self.data += part
        return not self.over

    def drop(self, n: int) -> None:
        del self.data[:n]
        self.base += n


class _Member:
    """The inflated bytes of the gzip member at a window's start, as a source; `fault` says how it failed: 'cut' or 'bad'."""

    def __init__(self, w: _Window) -> None:
        self.w, self.fed, self.fault, self.z = w, 0, "", zlib.decompressobj(31)

    def read(self, n: int) -> bytes:
        while not self.z.eof and not self.fault:
            part = self.z.unconsumed_tail
            if not part:
                if self.fed >= len(self.w.data) and not self.w.more():
                    self.fault = "cut"
                    break
                part = bytes(self.w.data[self.fed : self.fed + (1 << 16)])
                self.fed += len(part)
            before = self.z.copy()
            try:
                out = self.z.decompress(part, n)
            except zlib.error:
                out, self.fault = self._until(before, part), "bad"
            if out:
                return out
        return b""

    @staticmethod
    def _until(z, part: bytes) -> bytes:
        """What inflates before the fault."""
        out = []
        try:
            for n in range(len(part)):
                out.append(z.decompress(part[n : n + 1]))
        except zlib.error:
            pass
        return b"".join(out)

    def used(self) -> int:
        return self.fed - len(self.z.unused_data) - len(self.z.unconsumed_tail)


#: Bytes of records of one member that are held until its end is known.
HOLD = 16 << 20


def _has_digest(record: Record) -> bool:
    return record.headers.get("warc-block-digest", "").startswith("sha1:")  # parse() has compared it


def read(source, most: int = 1 << 30, inside: bool = False) -> Iterator[Record | Gap]:
    """Records and gaps of one archive, plain or gzip by member, in file order. source: has read(n).

    most: bytes of a record that is still read; a larger one counts as a gap. inside: these are a
    member's inflated bytes, where no further member is looked for.
    """
    w, bad, why = _Window(source), None, ""
    while True:
        while len(w.data) < 4096 and w.more():
            pass
        if not w.data:
            break
        step, got, reason = 0, [], "neither a gzip member nor a version line"
        if not inside and w.data.startswith(GZIP):
            m, held, any_record = _Member(w), 0, False

            def placed(items: list, end: int) -> list:
                for x in items:
                    x.begin, x.end = w.base, end
                return items

            for x in read(m, most, True):
                got.append(x)
                if isinstance(x, Gap):
                    continue
                any_record = True
                held += len(x.block)
                if held > HOLD and m.used() < len(w.data):
                    if bad is not None:
                        yield Gap(bad, w.base, why)
                        bad = None
                    yield from placed(got, w.base + m.used())
                    done = m.used()
                    m.fed -= done
                    w.drop(done)
                    got, held = [], 0
            if m.fault:
                reason = "gzip member does not inflate or its check fails"
                got = [x for x in got if isinstance(x, Record) and (m.fault == "cut" or _has_digest(x))]
                if got:
                    if bad is not None:
                        yield Gap(bad, w.base, why)
                        bad = None
                    yield from placed(got, w.base + m.used())
                    got = []
            elif any_record or not got:
                step = m.used()
                placed(got, w.base + step)
            else:
                reason, got = got[0].reason, []
        elif VERSION.match(bytes(w.data[:16])):
            try:
                while True:
                    try:
                        record, step = parse(bytes(w.data))
                        if step >= len(w.data) and w.more():
                            step = 0
                            continue
                        break
                    except ValueError as e:
                        if str(e) in ("block is cut short", "record head does not end") and len(w.data) <= most and w.more(max(1 << 20, len(w.data))):
                            continue
                        raise
                record.begin, record.end = w.base, w.base + step
                got.append(record)
            except ValueError as e:
                reason, step = str(e), 0
        if step:
            if bad is not None:
                yield Gap(bad, w.base, why)
                bad = None
            yield from got
            w.drop(step)
            continue
        if bad is None:
            bad, why = w.base, reason
        w.drop(1)
        while True:  # to the next place at which a record may begin
            line = VERSION.search(w.data)
            places = [p for p in (-1 if inside else w.data.find(GZIP), line.start() if line else -1) if p >= 0]
            line = None  # else it holds the buffer
            if places:
                w.drop(min(places))
                break
            if w.over:
                w.drop(len(w.data))
                break
            w.drop(max(0, len(w.data) - 15))
            w.more()
    if bad is not None:
        yield Gap(bad, w.base, why)


# ------------------------------------------------------------------------ Spark


def write_archives(records: DataFrame, folder: str, date: str = "2024-01-01T00:00:00Z", target: int = 64 << 20, level: int = 4) -> DataFrame:
    """Write archives of about `target` bytes; (file, n_records, n_bytes) of those that stand.

    records: page_id, url, payload (binary, null for a revisit), payload_bytes, payload_digest (hex),
    refers_to. Names hold a random part for each attempt, so a task that runs again leaves an orphan
    and never a torn or doubled archive: readers go by the returned list, which is materialised.
    """

    def run(batches):
        store, root = resolve(folder)
        store.create_dir(root, recursive=True)
        sink = name = None
        count = size = 0
        done: list[tuple] = []

        for batch in batches:
            for page, url, payload, full, digest, refers in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if sink is None:
                    name, count, size = f"pages-{uuid.uuid4().hex}.warc.gz", 0, 0
                    sink = store.open_output_stream(f"{root}/{name}", compression=None)
                bare = base64.b32encode(bytes.fromhex(digest)).decode()
                http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {full}\r\n\r\n".encode()
                block = http + (payload or b"")
                headers = [("WARC-Type", "response" if refers is None else "revisit"), ("WARC-Record-ID", f"<urn:page:{page}>"), ("WARC-Date", date)]
                if url:
                    headers.append(("WARC-Target-URI", re.sub(r"[\r\n]", " ", url)))
                if refers is not None:
                    headers += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", f"<urn:page:{refers}>")]
                headers += [("WARC-Payload-Digest", f"sha1:{bare}"), ("WARC-Block-Digest", f"sha1:{sha1_base32(block)}"), ("Content-Type", "application/http; msgtype=response")]
                data = member(encode(headers, block), level)
                sink.write(data)
                count, size = count + 1, size + len(data)
                if size >= target:
                    sink.close()
                    done.append((name, count, size))
                    sink = None
        if sink is not None:
            sink.close()
            done.append((name, count, size))
        if done:
            a, b, c = zip(*done, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b, pa.int64()), pa.array(c, pa.int64())], names=["file", "n_records", "n_bytes"])

    return C.cut(records.select("page_id", "url", "payload", "payload_bytes", "payload_digest", "refers_to").mapInArrow(run, "file string, n_records long, n_bytes long"))


READ_SCHEMA = "file string, begin_at long, end_at long, gap string, warc_type string, record_id string, target_uri string, refers_to string, payload_digest string, http_length long, payload binary"


def read_archives(files: DataFrame, folder: str, with_payload: bool = True) -> DataFrame:
    """Records of the archives named in files.file, and a row with `gap` set for each quarantined range.

    An archive is streamed by one task; a record's bytes are all that is held.
    """

    def run(batches):
        store, root = resolve(folder)
        names = READ_SCHEMA.replace(",", "").split()[::2]
        types = [pa.string(), pa.int64(), pa.int64(), *[pa.string()] * 6, pa.int64(), pa.binary()]

        def batch_of(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

        for batch in batches:
            for file in batch.column(0).to_pylist():
                rows, held = [], 0
                with store.open_input_stream(f"{root}/{file}", compression=None) as source:
                    for x in read(source):
                        if isinstance(x, Gap):
                            rows.append((file, x.begin, x.end, x.reason, *[None] * 7))
                        else:
                            http, payload = x.http()
                            size = http.get("content-length", "")
                            stated = x.headers.get("warc-payload-digest", "").removeprefix("sha1:") or None
                            digest = sha1_base32(payload) if x.kind == "response" else stated
                            rows.append((file, x.begin, x.end, None, x.kind, x.headers.get("warc-record-id"), x.headers.get("warc-target-uri"), x.headers.get("warc-refers-to"), digest, int(size) if size.isdigit() else None, payload if with_payload else None))
                            held += len(payload)
                        if len(rows) >= 4096 or held > 16 << 20:
                            yield batch_of(rows)
                            rows, held = [], 0
                if rows:
                    yield batch_of(rows)

    return files.select("file").mapInArrow(run, READ_SCHEMA)


def with_revisits(pages: DataFrame, least: int = 0) -> DataFrame:
    """Records to write for pages (page_id, url, html): of equal payloads of `least` bytes or more, the
    largest page_id holds the payload and the others refer to it."""
    body = pages.select(F.col("page_id").cast("long"), "url", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("payload"))
    body = body.withColumn("payload_bytes", F.octet_length("payload").cast("long")).withColumn("payload_digest", F.sha1("payload"))
    body = body.withColumn("key", F.coalesce("page_id", F.lit(-(1 << 63))))
    same = ["payload_digest", "payload_bytes"]
    ids = body.where(F.col("payload_bytes") >= least).select("key", "page_id", *same).distinct()  # a digest's rows are narrow here
    held = ids.groupBy(*same).agg(F.max("page_id").alias("holder"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    refers = ids.join(held, same).where(~F.col("holder").eqNullSafe(F.col("page_id"))).select("key", *same, F.col("holder").alias("refers_to"))
    out = body.join(refers, ["key", *same], "left").drop("key")  # payloads meet them by page, however many share a digest
    return out.withColumn("payload", F.when(F.col("refers_to").isNull(), F.col("payload")))


def round_trip(pages: DataFrame, least: int = 0) -> DataFrame:
    """Write a record per page, read the archives back: (page_id, payload_bytes, payload_digest, record_type, refers_to).

    A null page is an empty payload, a null page_id has a record id without a number. Rows that repeat
    a page with the same payload are each a record of the same type. Other columns are ignored. An
    empty table writes no archive. The digest of a response is taken of the payload that was read.
    """
    folder = C.work_dir(pages.sparkSession, "warc")
    files = write_archives(with_revisits(pages, least), folder)
    number = lambda c: F.regexp_extract(c, r"urn:page:(-?\d+)", 1).try_cast("long")
    back = read_archives(files.repartition(max(1, files.count())), folder).where("gap is null and warc_type in ('response', 'revisit')")
    return back.select(
        number("record_id").alias("page_id"),
        F.when(F.col("warc_type") == "response", F.octet_length("payload")).otherwise(F.col("http_length")).cast("long").alias("payload_bytes"),
        "payload_digest",
        F.col("warc_type").alias("record_type"),
        number("refers_to").alias("refers_to"),
    )


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages to archives and back."""
    return round_trip(C.table(spark, sf_dir, "pages"))
