"""WARC archives: a writer with revisit records, and a reader that verifies boundary chains.

An archive is a table of chunks, each with the bytes that follow it up to the longest header, so that any task can
read any chunk. A task offers every position of the magic as a candidate, with the offset that its header says the
next record has. Per archive, pointer jumping from the file's start over these links keeps the reachable
candidates; magic inside a payload is never reached, whatever follows it there. Records, and headers of any length,
that end beyond their chunk's bytes are put together from the chunks they cover. A chain that does not reach its
archive's last byte is an error.

Of records with equal payloads of at least ``least`` bytes, that with the largest page id is the response. Nulls in
html are empty payloads; a null url is written as about:blank. Rows with null ids revisit the largest id that has
their payload, and are responses where no id has it. Repeated rows with the largest id are all responses. Extra columns are ignored.
An empty table gives empty archives.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from embedvocab.llm.common import arrow_rows, columns, written

MAGIC = b"WARC/1."
#: Bytes of a chunk; of what follows it, which most headers do not exceed; of an archive, after which a new one begins.
CHUNK, LOOK_AHEAD, ARCHIVE = 512 << 10, 64 << 10, 1 << 30

_CHUNKS = pa.schema([("archive", pa.string()), ("chunk", pa.int64()), ("own", pa.int32()), ("data", pa.binary())])
_CHUNKS_DDL = "archive string, chunk long, own int, data binary"


# ---------------------------------------------------------------- writing

def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """A response, or a revisit of another page's response, which has the payload's head but not its bytes."""
    target = "".join(c for c in url or "about:blank" if c not in "\r\n") or "about:blank"
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    fields = [f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'none' if page_id is None else page_id}>", "WARC-Date: 2024-01-01T00:00:00Z",
              f"WARC-Target-URI: {target}", f"WARC-Payload-Digest: sha1:{digest}"]
    if refers_to is not None:
        fields += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    fields += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return b"WARC/1.1\r\n" + "\r\n".join(fields).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def chunks(archive: str, parts: Iterator[bytes], chunk: int, look_ahead: int) -> Iterator[tuple]:
    """Rows of the archive's bytes."""
    held, n = bytearray(), 0
    for part in parts:
        held += part
        while len(held) >= chunk + look_ahead:
            yield archive, n, chunk, bytes(held[:chunk + look_ahead])
            del held[:chunk]
            n += 1
    while held:
        yield archive, n, min(chunk, len(held)), bytes(held[:chunk + look_ahead])
        del held[:chunk]
        n += 1


def marked(pages: DataFrame, least: int = 1000) -> DataFrame:
    """(page_id, url, payload, digest, refers_to): which page's response each page revisits, if any."""
    rows = columns(pages, page_id="long", url="string", html="string").select(
        "page_id", "url", F.coalesce(F.encode("html", "UTF-8"), F.lit(b"")).alias("payload")).withColumn("digest", F.sha1("payload"))
    copies = (rows.filter(F.octet_length("payload") >= least).groupBy("digest")
              .agg(F.max("page_id").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("digest", "first"))
    # a table of the groups of copies alone; Spark broadcasts it if it is small and else deals out the pages, splitting hot groups
    refers = F.when(F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    return rows.join(written(copies), "digest", "left").select("page_id", "url", "payload", "digest", refers.alias("refers_to"))


def write(pages: DataFrame, least: int = 1000, chunk: int = CHUNK, look_ahead: int = LOOK_AHEAD) -> DataFrame:
    """The archives of the pages as a written table of chunks; one or more archives a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (r for b in batches for r in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True))
        task, number, row = TaskContext.get().partitionId(), 0, next(rows, None)
        while row is not None:
            size = 0

            def records() -> Iterator[bytes]:
                nonlocal row, size
                while row is not None and size < ARCHIVE:
                    out = record(*row)
                    size += len(out)
                    row = next(rows, None)
                    yield out

            for made in chunks(f"{task:06d}-{number:04d}.warc", records(), chunk, look_ahead):
                yield from arrow_rows(_CHUNKS, [made]).to_batches()
            number += 1

    return written(marked(pages, least).mapInArrow(run, _CHUNKS_DDL))


def chunks_of_files(spark: SparkSession, path: str, chunk: int = CHUNK, look_ahead: int = LOOK_AHEAD) -> DataFrame:
    """The same table from uncompressed WARC files that Spark can list."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, data in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                for made in chunks(name, iter([data.as_py()]), chunk, look_ahead):
                    yield from arrow_rows(_CHUNKS, [made]).to_batches()

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, _CHUNKS_DDL)


# ---------------------------------------------------------------- reading

_RECORDS = pa.schema([("archive", pa.string()), ("offset", pa.int64()), ("next", pa.int64()), ("record_type", pa.string()), ("page_id", pa.int64()), ("refers_to", pa.int64()),
                      ("said_digest", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("block_at", pa.int64()), ("block_bytes", pa.int64())])
_RECORDS_DDL = "archive string, offset long, next long, record_type string, page_id long, refers_to long, said_digest string, payload_bytes long, payload_digest string, block_at long, block_bytes long"


#: The type of the row that stands for an archive's end.
END = "end of archive"


def header(data: bytes, at: int) -> tuple[dict[bytes, bytes], int] | None:
    """The fields of the record header that may begin at a position, and where its block begins."""
    end = data.find(b"\r\n\r\n", at)
    if end < 0:
        return None
    version, *lines = data[at:end].split(b"\r\n")
    if len(version) != len(MAGIC) + 1 or not version[-1:].isdigit():
        return None
    fields = {k.strip().lower(): v.strip() for k, s, v in (line.partition(b":") for line in lines) if s}
    if not fields.get(b"content-length", b"").isdigit() or b"warc-type" not in fields:
        return None
    return fields, end + 4


def page_of(urn: bytes | None) -> int | None:
    number = (urn or b"").removeprefix(b"<urn:page:").removesuffix(b">")
    return int(number) if number.lstrip(b"-").isdigit() else None


def payload_of(block: bytes) -> tuple[int, bytes] | None:
    """The length that the head of an HTTP message gives, and the bytes after the head."""
    end = block.find(b"\r\n\r\n")
    if end < 0:
        return None
    said = [line.partition(b":")[2].strip() for line in block[:end].split(b"\r\n") if line.lower().startswith(b"content-length:")]
    body = block[end + 4:]
    return (int(said[0]) if said and said[0].isdigit() else len(body)), body


def begins(data: bytes, at: int) -> bool:
    """Whether the bytes, as far as they go, are those of a header that has no end yet."""
    line = data[at:at + len(MAGIC) + 3]
    return data.find(b"\r\n\r\n", at) < 0 and (line[len(MAGIC):-2].isdigit() and line.endswith(b"\r\n") or len(line) < len(MAGIC) + 3)


def candidates(archive: str, base: int, own: int, data: bytes) -> Iterator[tuple]:
    """Each position of the magic in a chunk that a header follows, with the offset of what would be the next record.

    A header without an end in the data has no next offset yet. The archive's last chunk, which nothing follows, adds its end as END.
    """
    if len(data) == own:
        yield (archive, base + own, -1, END, *[None] * 7)
    at = data.find(MAGIC, 0, own + len(MAGIC) - 1)
    while 0 <= at < own:
        found = header(data, at)
        if found:
            fields, block = found
            size = int(fields[b"content-length"])
            kind = fields[b"warc-type"].decode("latin-1")
            whole = block + size <= len(data)
            message = payload_of(data[block:block + size]) if whole else None
            body = message and (hashlib.sha1(message[1]).hexdigest() if kind == "response" else None)
            yield (archive, base + at, base + block + size + 4, kind, page_of(fields.get(b"warc-record-id")), page_of(fields.get(b"warc-refers-to")),
                   fields.get(b"warc-payload-digest", b"").decode("latin-1").removeprefix("sha1:"), message and (len(message[1]) if kind == "response" else message[0]), body, base + block, size)
        elif len(data) > own and begins(data, at):
            yield (archive, base + at, *[None] * 9)
        at = data.find(MAGIC, at + 1, own + len(MAGIC) - 1)


def completed(pending: DataFrame, archived: DataFrame, chunk: int) -> DataFrame:
    """The candidates whose headers end in a later chunk than their own, from (archive, offset); their blocks are read later."""
    blank = b"\r\n\r\n"

    def first_blank(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ends = [(b.column(1)[i].as_py(), data.as_py().find(blank)) for i, data in enumerate(b.column(2))]
            yield pa.record_batch([b.column(0), pa.array([n for n, _ in ends], pa.int64()), pa.array([n * chunk + e if e >= 0 else None for n, e in ends], pa.int64())], names=["archive", "last", "blank"])

    ends = archived.select("archive", "chunk", "data").mapInArrow(first_blank, "archive string, last long, blank long").filter("blank is not null")
    spans = pending.select("archive", "offset").join(ends, "archive").filter("blank > offset").groupBy("archive", "offset").agg(F.min("blank").alias("blank"))
    covered = spans.withColumn("chunk", F.explode(F.sequence(F.expr(f"offset div {chunk}"), F.expr(f"(blank + 3) div {chunk}"))))
    low, high = F.greatest(F.col("offset"), F.col("chunk") * chunk), F.least(F.col("blank") + 4, (F.col("chunk") + 1) * chunk)
    piece = F.substring("data", (low - F.col("chunk") * chunk + 1).cast("int"), (high - low).cast("int"))
    heads = (covered.join(archived.select("archive", "chunk", "data"), ["archive", "chunk"]).select("archive", "offset", F.struct("chunk", piece.alias("bytes")).alias("part"))
             .groupBy("archive", "offset").agg(F.array_sort(F.collect_list("part")).alias("parts")))

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for archive, offset, parts in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                head = b"".join(p["bytes"] for p in parts)
                yield from arrow_rows(_RECORDS, candidates(archive, offset, len(head) - 1, head) if header(head, 0) else []).slice(0, 1).to_batches()

    return heads.mapInArrow(parse, _RECORDS_DDL)


def reachable(offset: np.ndarray, after: np.ndarray) -> np.ndarray:
    """Which records a chain from offset 0 reaches, by pointer jumping; offsets are sorted."""
    n = len(offset)
    to = np.searchsorted(offset, after)
    jump = np.append(np.where((to < n) & (offset[np.minimum(to, n - 1)] == after), to, n), n)  # n: nowhere
    seen = np.zeros(n + 1, bool)
    seen[:1] = n > 0 and offset[0] == 0
    for _ in range(max(1, n.bit_length())):
        seen[jump[np.flatnonzero(seen)]] = True
        jump = jump[jump]
    return seen[:n]


def read(archived: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """The records of a table of chunks: archive, offset, record_type, page_id, refers_to, payload_bytes, payload_digest."""

    def offer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for archive, n, own, data in zip(*(b.column(i) for i in range(4)), strict=True):
                yield from arrow_rows(_RECORDS, candidates(archive.as_py(), n.as_py() * chunk, own.as_py(), data.as_py())).to_batches()

    def verify(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("offset")
        seen = reachable(rows.column("offset").to_numpy(), rows.column("next").to_numpy())
        end = rows.column("record_type").to_numpy(zero_copy_only=False) == END
        if not seen[end].any():
            raise ValueError(f"{rows.column('archive')[0]}: the chain of records ends before the archive does, after {max(rows.column('offset').to_numpy()[seen], default=0)}")
        return rows.filter(pa.array(seen & ~end))

    offered = written(archived.mapInArrow(offer, _RECORDS_DDL))
    pending, known = offered.filter("next is null"), offered.filter("next is not null")
    if not pending.isEmpty():
        known = known.unionByName(completed(pending, archived, chunk))
    found = written(known.groupBy("archive").applyInArrow(verify, _RECORDS_DDL))
    whole = found.filter("payload_bytes is not null")
    # the few that end beyond the bytes their chunk's task had
    long = found.filter("payload_bytes is null").withColumn("chunk", F.explode(F.sequence(F.expr(f"block_at div {chunk}"), F.expr(f"greatest(block_at, block_at + block_bytes - 1) div {chunk}"))))
    low, high = F.greatest(F.col("block_at"), F.col("chunk") * chunk), F.least(F.col("block_at") + F.col("block_bytes"), (F.col("chunk") + 1) * chunk)
    piece = F.substring("data", (low - F.col("chunk") * chunk + 1).cast("int"), (high - low).cast("int"))
    keys = [c for c in found.columns if c not in ("payload_bytes", "payload_digest")]
    parts = long.join(archived.select("archive", "chunk", "data"), ["archive", "chunk"]).select(*keys, F.struct("chunk", piece.alias("bytes")).alias("part"))
    blocks = parts.groupBy(*keys).agg(F.array_sort(F.collect_list("part")).alias("parts"))

    def together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                message = payload_of(b"".join(p["bytes"] for p in row.pop("parts"))) or (None, b"")
                full = row["record_type"] == "response"
                row |= {"payload_bytes": len(message[1]) if full else message[0], "payload_digest": hashlib.sha1(message[1]).hexdigest() if full else None}
                yield from arrow_rows(_RECORDS, [tuple(row[c] for c in _RECORDS.names)]).to_batches()

    everything = whole.unionByName(blocks.mapInArrow(together, _RECORDS_DDL))
    return everything.select("archive", "offset", "record_type", "page_id", "refers_to", "payload_bytes", F.coalesce("payload_digest", "said_digest").alias("payload_digest"))


def digest(pages: DataFrame) -> DataFrame:
    """What is read back of the pages' archives."""
    return read(write(pages)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


#: The same rows by definition.
ORACLE = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages),
c AS (SELECT payload_digest, max(page_id) AS latest FROM p WHERE payload_bytes >= 1000 GROUP BY 1)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN latest IS NULL OR page_id = latest THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN latest IS NOT NULL AND page_id <> latest THEN latest END AS refers_to
FROM p LEFT JOIN c USING (payload_digest)
"""
