"""WARC archives: a writer with revisit records and a salvage reader."""

from __future__ import annotations

import gzip
import hashlib
import os
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .blocks import flat
from .common import cut, shared_dir
from .exact_dedup import mark_copies

# Fixed values of the format.
VERSION = b"WARC/1.1"
GZIP_START = b"\x1f\x8b\x08"
END = b"\r\n\r\n"
VERSION_LINE = re.compile(rb"WARC/1\.[01]\r?\n")

ARCHIVE_BYTES = 16 << 20
STEP = 1 << 20
HEAD_STEP = 1 << 16
MIN_REVISIT = 100


def open_fs(path: str) -> tuple[pafs.FileSystem, str]:
    """File system and path inside it; the path may be of any store pyarrow knows."""
    return pafs.FileSystem.from_uri(re.sub(r"^file:/*", "file:///", path) if path.startswith("file:") else path)


def record(kind: str, fields: dict[str, str], block: bytes) -> bytes:
    """One record as a gzip member, with its block digest."""
    head = {"WARC-Type": kind, **fields}
    head["WARC-Block-Digest"] = "sha256:" + hashlib.sha256(block).hexdigest()
    head["Content-Length"] = str(len(block))
    lines = [VERSION.decode()] + [f"{k}: {v}" for k, v in head.items()]
    body = "\r\n".join(lines).encode() + END + block + END
    return gzip.compress(body, compresslevel=4, mtime=0)


def _clean(value: str) -> str:
    return re.sub(r"[\r\n]+", " ", value)


def page_record(page_id, url, payload: bytes, digest: str, refers_to, revisit: bool) -> bytes:
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    fields = {
        "WARC-Record-ID": f"<urn:page:{page_id}>",
        "WARC-Date": "2000-01-01T00:00:00Z",
        "WARC-Target-URI": _clean(url or ""),
        "WARC-Payload-Digest": f"sha256:{digest}",
        "WARC-Payload-Length": str(len(payload)),
        "Content-Type": "application/http; msgtype=response",
    }
    if revisit:
        fields["WARC-Refers-To"] = f"<urn:page:{refers_to}>"
        fields["WARC-Profile"] = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
        return record("revisit", fields, http)
    return record("response", fields, http + payload)


@dataclass
class Record:
    kind: str
    fields: dict[str, str]
    block: bytes
    start: int

    @property
    def payload(self) -> bytes:
        if self.fields.get("content-type", "").startswith("application/http"):
            return self.block.partition(END)[2]
        return self.block


@dataclass
class Salvage:
    """Reads an archive from start to end and goes on after what is broken.

    A record whose version line, headers, length or block digest fails is
    given up and the reader goes on at the next record, or version line, of the
    same member.  Of a member that is cut off or whose check sum fails, what can
    be inflated is read too, but only records with a block digest that holds
    count, and none if it is the member's only one; then the reader looks for the next place at which a member starts
    whose first bytes are a version line (in archives that are not compressed:
    the next version line) and goes on there.  ``gaps`` lists (start, end,
    reason) of the bytes passed over; within a member, as in ``Record.start``,
    a place is the member's start plus that in its content.  At most one member
    (or the headers of one record) and one step are held in memory.
    """

    file: object
    size: int
    gaps: list[tuple[int, int, str]] = field(default_factory=list)
    endless: int | None = None  # from here on no headers end

    def _at(self, start: int, length: int) -> bytes:
        self.file.seek(start)
        return self.file.read(max(0, min(length, self.size - start)))

    def _member(self, start: int) -> tuple[bytes, int, str]:
        """(content, end, what is wrong or '') of the gzip member at ``start``."""
        tool, out, at = zlib.decompressobj(31), [], start
        while not tool.eof:
            part = self._at(at, STEP)
            if not part:
                return b"".join(out), at, "truncated member"
            before = tool.copy()
            try:
                out.append(tool.decompress(part))
            except zlib.error as e:
                return b"".join(out) + self._before_error(before, part), at, str(e)
            at += len(part) - len(tool.unused_data)
        return b"".join(out), at, ""

    @staticmethod
    def _before_error(tool, part: bytes) -> bytes:
        """What a step that ends in an error inflates to before it."""
        out, at = [], 0
        for size in (4096, 64, 1):
            while at < len(part):
                before = tool.copy()
                try:
                    out.append(tool.decompress(part[at : at + size]))
                except zlib.error:
                    tool = before
                    break
                at += size
        return b"".join(out)

    def _starts(self, start: int) -> bool:
        """Whether a record seems to start here."""
        part = self._at(start, 512)
        if part.startswith(GZIP_START):
            try:
                part = zlib.decompressobj(31).decompress(part, 64)
            except zlib.error:
                return False
        return VERSION_LINE.match(part) is not None

    def _next(self, start: int) -> int:
        """First place from ``start`` on at which a record starts, or the end."""
        seek = re.compile(re.escape(GZIP_START) + rb"|WARC/1\.[01]\r?\n")
        at = start
        while at < self.size:
            part = self._at(at, STEP + 16)
            for m in seek.finditer(part):
                if m.start() < STEP and self._starts(at + m.start()):
                    return at + m.start()
            at += STEP
        return self.size

    @staticmethod
    def _head(body: bytes, at: int) -> tuple[str, dict[str, str], int, int]:
        if not VERSION_LINE.match(body, at):
            raise ValueError("no version line")
        end = body.find(END, at)
        if end < 0:
            raise ValueError("headers do not end")
        fields = {}
        for line in body[at:end].split(b"\r\n")[1:]:
            name, colon, value = line.partition(b":")
            if not colon:
                raise ValueError("header line without a colon")
            fields[name.strip().lower().decode("latin-1")] = value.strip().decode("utf-8", "replace")
        if not fields.get("content-length", "").isdigit():
            raise ValueError("no content length")
        return fields.get("warc-type", ""), fields, end + len(END), int(fields["content-length"])

    def _records(self, body: bytes, start: int, sound: bool) -> tuple[list[Record], list[tuple[int, int, str]]]:
        """(records, gaps) of a member's content; unless it is ``sound``, only records with a digest count."""
        found, gaps, at = [], [], 0
        while at < len(body):
            past = None
            try:
                kind, fields, first, length = self._head(body, at)
                block = body[first : first + length]
                if len(block) < length or body[first + length : first + length + 4] != END:
                    raise ValueError("block is not of the stated length")
                past = first + length + len(END)
                self._checked(fields, block)
                if not sound and not fields.get("warc-block-digest", "").startswith("sha256:"):
                    raise ValueError("no block digest in a broken member")
                found.append(Record(kind, fields, block, start + at))
            except ValueError as e:
                if past is None:
                    m = VERSION_LINE.search(body, at + 1)
                    past = m.start() if m else len(body)
                gaps.append((start + at, start + past, str(e)[:200]))
            at = past
        return ([] if not sound and len(found) == 1 and not gaps else found), gaps

    @staticmethod
    def _checked(fields: dict[str, str], block: bytes) -> None:
        name, _, stated = fields.get("warc-block-digest", "").partition(":")
        if name == "sha256" and hashlib.sha256(block).hexdigest() != stated:
            raise ValueError("block digest differs")

    def _headers_end(self, start: int) -> int:
        """End of the headers of the record that is not compressed at ``start``."""
        if not VERSION_LINE.match(self._at(start, 16)):
            raise ValueError("no version line")
        at = start
        while at < self.size and (self.endless is None or at < self.endless):
            k = self._at(at, HEAD_STEP + len(END) - 1).find(END)
            if k >= 0:
                return at + k + len(END)
            at += HEAD_STEP
        self.endless = min(start, self.size if self.endless is None else self.endless)
        raise ValueError("headers do not end")

    def _plain(self, start: int) -> tuple[Record, int]:
        """The record at ``start`` of an archive that is not compressed."""
        head = self._at(start, self._headers_end(start) - start)
        kind, fields, first, length = self._head(head, 0)
        body = self._at(start + first, length + len(END))
        if body[length:] != END:
            raise ValueError("block is not of the stated length")
        self._checked(fields, body[:length])
        return Record(kind, fields, body[:length], start), start + first + length + len(END)

    def records(self) -> Iterator[Record]:
        at = 0
        while at < self.size:
            try:
                if self._at(at, 3) == GZIP_START:
                    body, end, wrong = self._member(at)
                    found, gaps = self._records(body, at, not wrong)
                    if wrong or not found and gaps:  # the member's own bytes
                        end = self._next(at + 1) if wrong else end
                        gaps = [(at, end, wrong or gaps[0][2])]
                    self.gaps += gaps
                else:
                    one, end = self._plain(at)
                    found = [one]
            except ValueError as e:
                end = self._next(at + 1)
                self.gaps.append((at, end, str(e)[:200]))
                found = []
            yield from found
            at = end


def write_pages(
    pages: DataFrame, folder: str, page_id: str = "page_id", url: str = "url", html: str = "html"
) -> DataFrame:
    """Write every row of ``pages`` as a record of the archives in ``folder``.

    Returns (path, n_records, n_bytes) of the archives, already written.
    Payload is the html in UTF-8, null counts as empty.  Of records with equal
    payloads of at least 100 bytes the one with the smallest page_id is the
    response and the others are revisits that refer to it; a null page_id
    comes last.  Of repeated rows with that page_id one is the response.

    Which records are revisits is settled on digests (``mark_copies``), so
    pages that are certainly unique do not shuffle.  A task writes archives of
    about 16 MB under names of its own attempt and renames them when they are
    whole; only archives of attempts that ended well are in the result.
    """
    rows = pages.select(
        F.col(page_id).cast("long").alias("page_id"),
        F.col(url).cast("string").alias("url"),
        F.coalesce(F.col(html).cast("string"), F.lit("")).alias("html"),
    ).withColumn("digest", F.sha2("html", 256))
    small = F.octet_length("html") < MIN_REVISIT
    marked = mark_copies(rows, "digest", "page_id", largest=False).select(
        "page_id", "url", "html", "digest", "keep_id", (~F.col("kept") & ~small).alias("revisit")
    )
    store, root = open_fs(folder)
    store.create_dir(root)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        store, root = open_fs(folder)
        context, made = TaskContext.get(), []
        attempt = uuid.uuid4().hex
        out, count, size = None, 0, 0

        def close() -> None:
            nonlocal out, count, size
            if out is not None:
                out.close()
                name = f"{root}/part-{context.partitionId():06d}-{len(made):05d}-{attempt[:8]}.warc.gz"
                store.move(f"{root}/.{attempt}", name)
                made.append((os.path.basename(name), count, size))
            out, count, size = None, 0, 0

        for batch in batches:
            offsets, data = flat(batch.column("html"))
            at = offsets.tolist()
            cols = [batch.column(c).to_pylist() for c in ("page_id", "url", "digest", "keep_id", "revisit")]
            for k, (pid, link, digest, keep, revisit) in enumerate(zip(*cols)):
                one = page_record(pid, link, data[at[k] : at[k + 1]].tobytes(), digest, keep, revisit)
                if out is None:
                    out = store.open_output_stream(f"{root}/.{attempt}")
                out.write(one)
                count, size = count + 1, size + len(one)
                if size >= ARCHIVE_BYTES:
                    close()
        close()
        if made:
            yield pa.RecordBatch.from_arrays(
                [pa.array([m[0] for m in made]), pa.array([m[1] for m in made], pa.int64()), pa.array([m[2] for m in made], pa.int64())],
                ["path", "n_records", "n_bytes"],
            )

    return cut(marked.mapInArrow(work, "path string, n_records long, n_bytes long"))


FIELDS = "path string, offset long, kind string, record_id string, url string, digest string, refers_to string, payload_length long, payload binary, gap_end long, gap_reason string"


def read_archives(names: DataFrame, folder: str) -> DataFrame:
    """Records, and the gaps, of the archives ``names.path`` in ``folder``.

    A row with ``kind`` 'gap' tells of bytes [offset, gap_end) that no record
    was found in, and why.  An archive that cannot be opened is one gap.
    ``digest`` is that of the payload read, or for revisits the stated one.
    """

    def rows(path: str) -> Iterator[tuple]:
        store, root = open_fs(folder)
        try:
            with store.open_input_file(f"{root}/{path}") as f:
                reader = Salvage(f, f.size())
                for r in reader.records():
                    revisit = r.kind == "revisit"
                    payload = b"" if revisit else r.payload
                    stated = r.fields.get("warc-payload-digest", "").partition(":")[2]
                    length = r.fields.get("warc-payload-length", "") if revisit else str(len(payload))
                    digest = stated if revisit else hashlib.sha256(payload).hexdigest()
                    yield (path, r.start, r.kind, r.fields.get("warc-record-id"), r.fields.get("warc-target-uri"), digest, r.fields.get("warc-refers-to"), int(length) if length.isdigit() else None, payload, None, None)
                for start, end, why in reader.gaps:
                    yield (path, start, "gap", None, None, None, None, None, None, end, why)
        except FileNotFoundError as e:
            yield (path, 0, "gap", None, None, None, None, None, None, 0, str(e)[:200])

    names_of = [f.split()[0] for f in FIELDS.split(", ")]
    types = [pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.binary(), pa.int64(), pa.string()]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path in batch.column("path").to_pylist():
                held, size = [], 0
                for row in rows(path):
                    held.append(row)
                    size += len(row[8] or b"") + 500
                    if size > 4 << 20:
                        yield _batch(held)
                        held, size = [], 0
                if held:
                    yield _batch(held)

    def _batch(held: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held), types)], names_of)

    return names.select("path").mapInArrow(work, FIELDS)


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def page_records(records: DataFrame, strict: bool = False) -> DataFrame:
    """The pages' own columns from ``read_archives`` of archives by ``write_pages``.

    With ``strict`` a gap in an archive is an error that names its bytes;
    otherwise its pages are missing here, and told of by the gap's row alone.
    """
    number = lambda c: F.regexp_extract(c, r"<urn:page:(-?\d+)>", 1).try_cast("long")
    page_id = number("record_id")
    if strict:
        lost = F.format_string("bytes %d to %d of %s: %s", "offset", "gap_end", "path", "gap_reason")
        page_id = F.when(F.col("kind") == "gap", F.raise_error(lost).cast("long")).otherwise(page_id)
    kinds = ["response", "revisit"] + ["gap"] * strict
    return records.where(F.col("kind").isin(kinds)).select(
        page_id.alias("page_id"),
        F.col("payload_length").alias("payload_bytes"),
        F.col("digest").alias("payload_digest"),
        F.col("kind").alias("record_type"),
        F.when(F.col("kind") == "revisit", number("refers_to")).alias("refers_to"),
    )
