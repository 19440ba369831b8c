"""WARC archives: written with segmentation and chunked framing, read back by segment reassembly.

Archives are written by Spark's text writer, whose line end is the blank line that ends a record, so
they go to any store that Spark can write and a failed task leaves nothing behind. The reader streams
the same pieces and joins them again by Content-Length; it holds one record at a time, whatever the
archive's size. Segments of a record are grouped by the id of its first record and put in order of
their numbers; a record whose numbers have a hole or whose total length differs is reported, not guessed.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from qacurate.llm.text import slices
from qacurate.staging import Staged, bound_batches

END = b"\r\n\r\n"
_NO_PAGE = -(1 << 63)
_DATE = "2024-01-01T00:00:00Z"
_SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORD = "page_id long, record_id string, record_type string, refers_to long, url string, payload_bytes long, payload_digest string, segments int, problem string, payload binary"
_RECORD = pa.schema([("page_id", pa.int64()), ("record_id", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("segments", pa.int32()), ("problem", pa.string()), ("payload", pa.binary())])


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page: int | None, sha: str, copy: int) -> str:
    return f"<urn:uuid:{uuid.uuid5(_SPACE, f'{page}/{sha}/{copy}')}>"


def frame(body: bytes, size: int) -> bytes:
    """Chunked transfer framing in chunks of ``size`` bytes."""
    parts = [b"%x\r\n%s\r\n" % (len(c), c) for c in (body[i : i + size] for i in range(0, len(body), size))]
    return b"".join(parts) + b"0" + END


def unframe(body: bytes) -> bytes:
    """The payload of a chunked body; chunk extensions and trailers are passed over."""
    out, at = [], 0
    while True:
        line = body.index(b"\r\n", at)
        size = int(body[at:line].split(b";")[0], 16)
        at = line + 2
        if size == 0:
            return b"".join(out)
        if body[at + size : at + size + 2] != b"\r\n":
            raise ValueError("a chunk does not end where its size says")
        out.append(body[at : at + size])
        at += size + 2


def _head(fields: list[tuple[str, object]]) -> bytes:
    clean = (f"{k}: {' '.join(str(v).split())}" for k, v in fields if v is not None)
    return "\r\n".join(["WARC/1.1", *clean]).encode() + END


def records(page: int | None, url: str | None, payload: bytes, sha: str, copy: int, first: int | None, segment: int, chunk: int) -> Iterator[bytes]:
    """A page's records without the blank line that ends each: one, or the segments of a long one."""
    own, name = record_id(page, sha, copy), digest(payload)
    common = [("WARC-Date", _DATE), ("WARC-Target-URI", url), ("X-Page-Id", page), ("WARC-Payload-Digest", f"sha1:{name}")]
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
    if first is not None:
        block = http + b"Content-Length: %d" % len(payload) + END
        refers = [("WARC-Profile", _PROFILE), ("WARC-Refers-To", record_id(first, sha, 0)), ("X-Refers-To-Page", first)]
        yield _head([("WARC-Type", "revisit"), ("WARC-Record-ID", own), *common, *refers, ("Content-Type", "application/http; msgtype=response"), ("Content-Length", len(block))]) + block
        return
    if len(payload) > chunk:
        block = http + b"Transfer-Encoding: chunked" + END + frame(payload, chunk)
    else:
        block = http + b"Content-Length: %d" % len(payload) + END + payload
    pieces = [block[i : i + segment] for i in range(0, len(block), segment)]
    kind = [("Content-Type", "application/http; msgtype=response"), ("WARC-Segment-Number", 1 if len(pieces) > 1 else None), ("Content-Length", len(pieces[0]))]
    yield _head([("WARC-Type", "response"), ("WARC-Record-ID", own), *common, *kind]) + pieces[0]
    for n, piece in enumerate(pieces[1:], 2):
        total = len(block) if n == len(pieces) else None
        fields = [("WARC-Date", _DATE), ("WARC-Target-URI", url), ("WARC-Segment-Origin-ID", own), ("WARC-Segment-Number", n), ("WARC-Segment-Total-Length", total), ("Content-Length", len(piece))]
        yield _head([("WARC-Type", "continuation"), ("WARC-Record-ID", record_id(page, f"{sha}/{n}", copy)), *fields]) + piece


def plan_revisits(pages: DataFrame, least: int = 0) -> DataFrame:
    """Adds sha, copy and first: the page that a record revisits, null for responses.

    Of equal payloads of at least ``least`` bytes the smallest page_id is the response. Rows that repeat
    that page_id are responses as well; among pages without an id all are. The decision is an aggregate
    of ids by payload digest, so html meets it by page and not by payload, and no payload is hot.
    """
    # A page without an id gets one below all others here, so that join and window share one exchange of the html.
    rows = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumn("sha", F.sha1("payload")).withColumn("p", F.coalesce("page_id", F.lit(_NO_PAGE)))
    ids = rows.where(F.length("payload") >= least).select("page_id", "p", "sha")
    # Written before the join, whose large partitions (equal payloads) Spark then splits.
    low = Staged(ids.groupBy("sha").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1 and first is not null"), "first-pages").df
    later = ids.join(low, "sha").where(F.col("p") != F.col("first")).select("p", "sha", "first").distinct()
    copy = F.row_number().over(Window.partitionBy("p", "sha").orderBy("url")) - 1
    return rows.join(later, ["p", "sha"], "left").select("page_id", "url", "payload", "sha", copy.alias("copy"), "first")


def write_warc(pages: DataFrame, path: str, segment: int = 16 << 10, chunk: int = 8 << 10, per_file: int = 20_000, least: int = 0) -> None:
    """Writes a record for every page row (page_id, url, html) as gzip archives under ``path``.

    Null html is an empty payload. segment, chunk: bytes from which blocks are cut into records and
    payloads into chunks. per_file: page and continuation records of an archive at most.
    """
    bound_batches(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "payload"):
            out = [r for row in batch.to_pylist() for r in records(row["page_id"], row["url"], row["payload"], row["sha"], row["copy"], row["first"], segment, chunk)]
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], names=["value"])

    made = plan_revisits(pages, least).mapInArrow(run, "value binary").select(F.col("value").cast("string"))
    made.write.option("lineSep", END.decode()).option("compression", "gzip").option("maxRecordsPerFile", per_file).text(path)


def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of each record, from the pieces of archives in order.

    Pieces and the blank lines between them make up the archive's bytes again; records are cut from
    those by Content-Length alone, since a block may itself hold or end in parts of a blank line.
    """
    file, held, need, fields = None, bytearray(), 1, None

    def finish() -> None:
        if fields is not None or held.strip(b"\r\n"):
            raise ValueError(f"{file} ends inside a record")

    for batch in batches:
        for name, piece in zip(batch.column("file").to_pylist(), batch.column("value").to_pylist(), strict=True):
            if name != file:
                finish()
                file, held, need, fields = name, bytearray(), 1, None
            held += piece
            held += END
            while len(held) >= need:
                if fields is None:
                    at = len(held) - len(held.lstrip(b"\r\n"))
                    end = held.find(END, at)
                    if end < 0:
                        break
                    first, *lines = bytes(held[at:end]).split(b"\r\n")
                    if not first.startswith(b"WARC/"):
                        raise ValueError(f"{file}: a record begins with {first[:40]!r}")
                    fields = {k.strip().lower(): v.strip() for k, _, v in (x.decode("utf-8", "replace").partition(":") for x in lines)}
                    del held[: end + len(END)]
                    need = int(fields["content-length"])
                else:
                    block = bytes(held[:need])
                    del held[:need]
                    yield fields, block
                    fields, need = None, 1
    finish()


def _number(text: str | None) -> int | None:
    return None if text is None else int(text)


def _decoded(fields: dict[str, str], block: bytes, segments: int, problem: str | None, with_payload: bool) -> tuple:
    """A row of RECORD."""
    payload, size, name = None, None, None
    if problem is None:
        try:
            head, _, body = block.partition(END)
            http = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in head.split(b"\r\n")[1:])}
            stated = fields.get("warc-payload-digest", "").removeprefix("sha1:") or None
            if fields["warc-type"] == "revisit":
                size, name = int(http[b"content-length"]), stated
            else:
                payload = unframe(body) if http.get(b"transfer-encoding", b"").lower() == b"chunked" else body
                size, name = len(payload), digest(payload)
                if stated not in (None, name):
                    problem = "the payload differs from its digest"
        except (ValueError, KeyError) as e:
            problem = f"{type(e).__name__}: {e}"
    return (_number(fields.get("x-page-id")), fields["warc-record-id"], fields["warc-type"], _number(fields.get("x-refers-to-page")), fields.get("warc-target-uri"), size, name, segments, problem, payload if with_payload else None)


def _table(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else ([] for _ in _RECORD)
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(columns, _RECORD, strict=True)], schema=_RECORD)


def assemble(parts: list[tuple[int, dict[str, str], bytes]]) -> tuple[dict[str, str], bytes, str | None]:
    """Header of the first segment, joined block, and what is wrong; parts come in order of their numbers."""
    numbers, fields = [n for n, _, _ in parts], parts[0][1]
    block = b"".join(b for _, _, b in parts)
    total = _number(parts[-1][1].get("warc-segment-total-length"))
    if numbers != list(range(1, len(parts) + 1)):
        return fields, block, f"segment numbers {numbers[:20]}"
    if total != len(block):
        return fields, block, f"total length {total}, found {len(block)}"
    return fields, block, None


def read_warc(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """Every response and revisit record under ``path`` (RECORD); ``problem`` says why a payload is missing.

    A revisit record has no payload; its size and digest are those its headers state. Continuations
    without their first record are reported under its id. No archives with records: no rows.
    """
    bound_batches(spark)
    pieces = spark.read.option("lineSep", END.decode()).text(path).select(F.col("_metadata.file_path").alias("file"), F.col("value").cast("binary").alias("value"))

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, held = [], 0
        for fields, block in _parse(batches):
            if "warc-segment-number" not in fields and fields["warc-type"] in ("response", "revisit"):
                out.append(_decoded(fields, block, 1, None, with_payload))
                held += len(block)
                if len(out) >= 2000 or held > 8 << 20:
                    yield _table(out)
                    out, held = [], 0
        yield _table(out)

    def segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for fields, block in _parse(batches):
            if "warc-segment-number" in fields:
                origin = fields.get("warc-segment-origin-id", fields["warc-record-id"])
                row = [pa.array([origin]), pa.array([int(fields["warc-segment-number"])], pa.int32()), pa.array([list(fields)]), pa.array([list(fields.values())]), pa.array([block], pa.binary())]
                yield pa.RecordBatch.from_arrays(row, names=["origin", "number", "names", "fields", "block"])

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        origin, parts = None, []

        def close() -> pa.RecordBatch:
            fields, block, problem = assemble(parts)
            if fields["warc-type"] == "continuation":
                fields = {**fields, "warc-record-id": origin, "warc-type": "response"}
            return _table([_decoded(fields, block, len(parts), problem, with_payload)])

        for batch in batches:
            for row in batch.to_pylist():
                if parts and row["origin"] != origin:
                    yield close()
                    parts = []
                origin = row["origin"]
                parts.append((row["number"], dict(zip(row["names"], row["fields"], strict=True)), row["block"]))
        if parts:
            yield close()

    cut = pieces.mapInArrow(segments, "origin string, number int, names array<string>, fields array<string>, block binary")
    long_ = cut.repartition("origin").sortWithinPartitions("origin", "number").mapInArrow(joined, RECORD)
    return pieces.mapInArrow(whole, RECORD).union(long_)


def round_trip_sql(tables: str = "pages") -> str:
    """Oracle of the round trip: base32 worked out from the hexadecimal digest, five digits to four letters."""
    return f"""
with p as (
  select page_id, encode(coalesce(html, '')) as b, sha1(coalesce(html, '')) as h from {tables}
), g as (select *, min(page_id) over (partition by h) as low from p)
select page_id, octet_length(b)::bigint as payload_bytes,
  array_to_string(list_transform(range(32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + ((('0x' || substr(h, 5 * (k // 4)::int + 1, 5))::bigint >> (15 - 5 * (k % 4))::int) & 31), 1)), '') as payload_digest,
  case when page_id = low then 'response' else 'revisit' end as record_type,
  case when page_id <> low then low end as refers_to
from g
"""
