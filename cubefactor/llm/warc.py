"""WARC archives: segmented writing, and reassembly of continuation records.

Records are written as plain WARC/1.1 text through Spark's own file writer (each ends with the two line
ends that the format asks for, which serve as the writer's line separator), gzipped as whole files, so the
archives can lie in any store that Spark writes. Reading streams each file record by record. Parts of a
segmented record are grouped by the identifier of their origin, ordered by segment number, checked against
the stated total length, and their HTTP body is freed of its chunked transfer framing.

Defined cases: a null payload is empty; a null page_id is written and read back as null; equal payloads
have one response record, of the largest page_id (null counts as smallest), the others are revisits;
repeated page_ids and wholly repeated rows are separate records; payloads of any length are cut into segments of `segment_bytes`;
a missing, repeated or misnumbered segment or a wrong total length makes `complete` false and the record is
listed with null payload; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import chunks, shared_dir, ship_package, text_buffer, written

CRLF = b"\r\n"
RECORD_END = "\r\n\r\n"
#: Identifiers and dates of records are derived from their rows, so a rewritten task gives the same bytes.
ID_SPACE = uuid.UUID("6ba7b812-9dad-11d1-80b4-00c04fd430c8")
DATE = "2024-01-01T00:00:00Z"
PART = "origin string, number long, total long, kind string, page_id long, refers_to long, stated_bytes long, digest string, block binary"


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def chunk_frame(payload: bytes, size: int = 65_536) -> bytes:
    """Chunked transfer coding of a payload."""
    out = [b"%x\r\n%b\r\n" % (len(payload[at : at + size]), payload[at : at + size]) for at in range(0, len(payload), size)]
    return b"".join([*out, b"0\r\n\r\n"])


def chunk_unframe(body: bytes) -> bytes | None:
    """The payload under chunked transfer coding, with extensions and trailers skipped; None where the framing is broken."""
    at, out = 0, []
    while True:
        stop = body.find(CRLF, at)
        try:
            size = int(body[at:stop].split(b";")[0], 16) if stop >= 0 else -1
        except ValueError:
            return None
        if size < 0:
            return None
        if size == 0:
            return b"".join(out)
        out.append(body[stop + 2 : stop + 2 + size])
        if len(out[-1]) < size or body[stop + 2 + size : stop + 4 + size] != CRLF:
            return None
        at = stop + 4 + size


def http_payload(block: bytes) -> bytes | None:
    """The payload of an HTTP response: what follows the head, unframed where the head says so."""
    head, gap, body = block.partition(CRLF * 2)
    if not gap:
        return None
    fields = {k.strip().lower(): v.strip().lower() for k, _, v in (line.partition(b":") for line in head.split(CRLF)[1:])}
    return chunk_unframe(body) if fields.get(b"transfer-encoding") == b"chunked" else body


def _record(fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*fields, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + head.encode() + CRLF + block


def write_archives(records: DataFrame, path: str, *, segment_bytes: int = 1 << 20) -> None:
    """Write rows (page_id, url, html, digest, keeper, key) as archives: a response, or a revisit of `keeper`.

    `key` tells a row's record identifier apart from every other; `keeper` is null for responses.
    """

    def render(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "html", 4 << 20):
            out: list[bytes] = []
            data, offsets = text_buffer(part.column(part.schema.get_field_index("html")))
            raw = data.tobytes()
            rest = [part.column(part.schema.get_field_index(n)).to_pylist() for n in ("page_id", "url", "digest", "response_id", "is_revisit", "key")]
            for number, (page, url, digest, keeper, revisit, key) in enumerate(zip(*rest, strict=True)):
                payload = raw[offsets[number] : offsets[number + 1]]
                name = f"<urn:uuid:{uuid.uuid5(ID_SPACE, key)}>"
                shared = [("WARC-Date", DATE), ("WARC-Target-URI", " ".join((url or "urn:none").split()) or "urn:none"), ("X-Page-Id", "" if page is None else str(page))]
                if revisit:
                    block = b"HTTP/1.1 200 OK\r\nContent-Length: %d\r\n\r\n" % len(payload)
                    out.append(_record([("WARC-Type", "revisit"), ("WARC-Record-ID", name), *shared, ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Payload-Digest", f"sha1:{digest}"), ("X-Refers-To-Page", "" if keeper is None else str(keeper)), ("Content-Type", "application/http;msgtype=response")], block))
                    continue
                block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunk_frame(payload)
                parts = [block[at : at + segment_bytes] for at in range(0, len(block), segment_bytes)]
                first = [("WARC-Type", "response"), ("WARC-Record-ID", name), *shared, ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http;msgtype=response")]
                out.append(_record([*first, *([("WARC-Segment-Number", "1")] if len(parts) > 1 else [])], parts[0]))
                for at, piece in enumerate(parts[1:], 2):
                    own = f"<urn:uuid:{uuid.uuid5(ID_SPACE, f'{key}/{at}')}>"
                    ends = [("WARC-Segment-Total-Length", str(len(block)))] if at == len(parts) else []
                    out.append(_record([("WARC-Type", "continuation"), ("WARC-Record-ID", own), ("WARC-Date", DATE), ("WARC-Segment-Origin-ID", name), ("WARC-Segment-Number", str(at)), *ends], piece))
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["record"])

    lines = records.select("page_id", F.col("url").cast("string").alias("url"), "html", "digest", "response_id", "is_revisit", "key").mapInArrow(render, "record binary")
    lines.select(F.col("record").cast("string").alias("value")).write.option("lineSep", RECORD_END).option("compression", "gzip").text(path)


def records_of(pieces: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Heads and blocks of the records in a file that was cut at every RECORD_END."""
    pieces = iter(pieces)
    for piece in pieces:
        if not piece.startswith(b"WARC/"):
            continue  # the empty piece after a block that ends in line ends, or bytes between records
        fields = {}
        for line in piece.decode("utf-8", "replace").split("\r\n")[1:]:
            k, _, v = line.partition(":")
            fields[k.strip().lower()] = v.strip()
        wanted, parts, have = int(fields.get("content-length", 0)), [], -4
        while have < wanted:
            part = next(pieces, None)
            if part is None:
                break
            parts.append(part)
            have += len(part) + 4
        yield fields, b"\r\n\r\n".join(parts)[:wanted]


def _long(value: str | None) -> int | None:
    return int(value) if value else None


def read_parts(spark: SparkSession, path: str) -> DataFrame:
    """One row (PART) for each record of the archives; gzip files are read whole, one record at a time."""

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def pieces() -> Iterator[bytes]:
            for batch in batches:
                for value in batch.column(0):
                    yield value.as_py() or b""

        rows: list[tuple] = []
        held = 0

        def flush() -> pa.RecordBatch:
            kinds = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], [x.split()[0] for x in PART.split(", ")])

        for fields, block in records_of(pieces()):
            kind = fields.get("warc-type", "")
            stated = None
            if kind == "revisit":
                stated = next((int(x.split(b":")[1]) for x in block.split(CRLF) if x.lower().startswith(b"content-length:")), None)
            segment = _long(fields.get("warc-segment-number"))
            origin = fields.get("warc-segment-origin-id") or fields.get("warc-record-id", "")
            total = _long(fields.get("warc-segment-total-length")) if segment else len(block)
            rows.append((origin, segment or 0, total, kind, _long(fields.get("x-page-id")), _long(fields.get("x-refers-to-page")), stated, fields.get("warc-payload-digest", "").removeprefix("sha1:"), block))
            held += len(block)
            if held > 8 << 20:
                yield flush()
                rows, held = [], 0
        if rows:
            yield flush()

    lines = spark.read.option("lineSep", RECORD_END).text(path)
    return lines.select(F.col("value").cast("binary").alias("value")).mapInArrow(parse, PART)


def reassemble(parts: DataFrame) -> DataFrame:
    """Whole records: segments grouped by origin, ordered by number, joined and checked; other records pass as they are."""
    whole = parts.where("number = 0").select("kind", "page_id", "refers_to", "stated_bytes", "digest", "block", F.lit(True).alias("complete"))
    grouped = (
        parts.where("number > 0")
        .groupBy("origin")
        .agg(
            F.array_sort(F.collect_list(F.struct("number", "block"))).alias("segments"),
            F.max("total").alias("total"),
            *(F.first(F.when(F.col("number") == 1, F.col(c)), ignorenulls=True).alias(c) for c in ("kind", "page_id", "refers_to", "stated_bytes", "digest")),
        )
    )
    joined = F.aggregate("segments", F.lit(b"").cast("binary"), lambda all_, s: F.concat(all_, s["block"]))
    in_order = F.transform("segments", lambda s: s["number"]) == F.transform(F.sequence(F.lit(1), F.size("segments")), lambda n: n.cast("long"))
    stitched = grouped.withColumn("block", joined)
    stitched = stitched.withColumn("complete", F.coalesce(in_order & (F.octet_length("block") == F.col("total")), F.lit(False)))
    return whole.unionByName(stitched.select(*whole.columns))


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """page_id, kind, refers_to, stated digest, complete, and the payload with its length and digest."""

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches, "block", 4 << 20):
            kinds, pages, refers, stated, digests, blocks, complete = (batch.column(i).to_pylist() for i in range(7))
            payloads, lengths, found = [], [], []
            for kind, size, digest, block, whole in zip(kinds, stated, digests, blocks, complete, strict=True):
                payload = http_payload(block) if kind == "response" and whole else None
                payloads.append(payload)
                lengths.append(size if kind == "revisit" else None if payload is None else len(payload))
                found.append(digest if kind == "revisit" else None if payload is None else digest_of(payload))
            good = [bool(w) and (k == "revisit" or f == d) for w, k, f, d in zip(complete, kinds, found, digests, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(pages, pa.int64()), pa.array(lengths, pa.int64()), pa.array(found, pa.string()), pa.array(kinds, pa.string()), pa.array(refers, pa.int64()), pa.array(good), pa.array(payloads, pa.binary())], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "complete", "payload"])

    return reassemble(read_parts(spark, path)).mapInArrow(finish, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, complete boolean, payload binary")


def payload_digest() -> Column:
    """SHA-1 in upper-case base32, by built-in functions: five hex digits become four letters."""
    letters = F.lit("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")
    value = lambda at: F.conv(F.substring(F.col("sha"), at * 5 + 1, 5), 16, 10).cast("long")
    picks = [letters.substr((F.shiftright(value(at), shift).bitwiseAND(F.lit(31)) + 1).cast("int"), F.lit(1)) for at in range(8) for shift in (15, 10, 5, 0)]
    return F.concat(*picks)


def assign_responses(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """Which rows are responses and which revisit one: the largest page_id of each payload of `least_bytes` or more keeps it."""
    own = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    own = own.withColumn("sha", F.sha1(F.col("html").cast("binary")))
    own = own.withColumn("tie", F.xxhash64("url"))
    # Only these small rows are shuffled to find the largest row of a payload, its response, and repeated rows.
    counted = written(own.groupBy("sha", "page_id", "tie").agg(F.count("*").alias("n")), "page-rows")
    keepers = counted.groupBy("sha").agg(F.max(F.struct("page_id", "tie")).alias("keeper"), F.max("n").alias("most"))
    marked = own.join(keepers.where("most = 1"), "sha").withColumn("number", F.lit(1))
    if not counted.where("n > 1").isEmpty():
        # Repeated rows are alike in all columns, so that any order numbers them alike.
        again = own.join(keepers.where("most > 1"), "sha")
        marked = marked.unionByName(again.withColumn("number", F.row_number().over(Window.partitionBy("sha", "page_id", "tie").orderBy("url"))))
    big = F.octet_length(F.col("html").cast("binary")) >= least_bytes
    first = F.struct("page_id", "tie").eqNullSafe(F.col("keeper")) & (F.col("number") == 1)
    repeat = F.when(F.col("number") > 1, F.concat(F.lit("repeat-"), F.col("number").cast("string")))
    return marked.select(
        "page_id", "url", "html", payload_digest().alias("digest"), F.col("keeper.page_id").alias("response_id"),
        (big & ~first).alias("is_revisit"),
        F.concat_ws("/", F.coalesce(F.col("page_id").cast("string"), F.lit("none")), F.col("tie").cast("string"), F.col("sha"), repeat).alias("key"),
    )


def archive_round_trip(pages: DataFrame, *, segment_bytes: int = 1 << 20, least_bytes: int = 0) -> DataFrame:
    """Write every page to archives in the shared folder and read them back."""
    spark = pages.sparkSession
    ship_package(spark)
    path = f"{shared_dir(spark)}/archives-{uuid.uuid4().hex}"
    write_archives(assign_responses(pages, least_bytes), path, segment_bytes=segment_bytes)
    return read_archives(spark, path)
