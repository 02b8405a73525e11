"""WARC archives as a chunked record table.

A record is a row for each of its chunks: (record, chunk number, bytes), none longer than `chunk` bytes. The payloads
are cut where the table is read, so workers get one chunk at a time and carry the running digest of each record from
chunk to chunk; no step there needs a whole payload. In the archive an oversized record is a first segment and
`continuation` records, as the format has it, so every archive record is bounded. Records are written by Spark's text
sink, one row each, with the record's closing line ends as the separator, to any store that Spark can write to; each
file begins with a `warcinfo` record. Files aren't compressed by default: the sink could only compress a file as one
stream, and readers of the format expect one stream for each record.

Archives are read by Spark's text source with the start of a record as the separator, which streams files of any size.
A payload that holds a version line is cut into segments inside it, so no record block, not even with the line ends
around it, holds the mark and every row read is one record. A payload is put together again chunk by chunk in order,
updating its digest.

Contract: null payloads count as empty; equal payloads of at least `least` bytes are kept once, under the
smallest page_id, and the others are `revisit` records that refer to it (by WARC-Refers-To, too, unless rows repeat it); null urls are left out of the
header; repeated page ids are records of their own; an empty table gives an empty archive.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinetrace.llm.storage import fresh_path, written

# The format's version line, line end and record end.
VERSION, LINE, RECORD_END = b"WARC/1.1", b"\r\n", b"\r\n\r\n"
MARK = RECORD_END + VERSION + LINE
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
CHUNK, LEAST = 1 << 20, 100
DATE = "2024-01-01T00:00:00Z"
#: Digests with more than one page that may be broadcast (about 100 bytes each); more are joined by a shuffle.
BROADCAST_DIGESTS = 200_000


def classified(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """page_id, url, payload, digest, size, record_type, refers_to, and whether the response's record can be named (`named`) of every page."""
    rows = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), F.encode(F.coalesce(F.col("html").cast("string"), F.lit("")), "UTF-8").alias("payload"))
    keyed = rows.withColumn("size", F.octet_length("payload").cast("bigint")).withColumn("digest", F.sha2("payload", 256))
    same = keyed.where(F.col("size") >= least).groupBy("digest", "page_id").agg(F.count("*").alias("n"))
    first = F.min(F.when(F.col("page_id").isNotNull(), F.struct("page_id", "n"))).alias("first")
    shared = same.groupBy("digest").agg(first, F.sum("n").alias("all")).where("`all` > 1")
    shared = written(shared.select("digest", F.col("first.page_id").alias("first"), (F.col("first.n") == 1).alias("named")), "shared")
    joined = keyed.join(F.broadcast(shared) if shared.count() <= BROADCAST_DIGESTS else shared, "digest", "left")
    revisit = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    return joined.select(
        "page_id", "url", "payload", "digest", "size", F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("first")).alias("refers_to"), F.coalesce("named", F.lit(False)).alias("named")
    )


def record_name(page_id: int | None, row: int | str) -> str:
    """The name of a page's record by its row, or by its digest: that of a response that others refer to and that no row repeats."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{row}')}>"


def chunk_rows(pages: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """What `classified` gives with a row for each chunk of at most `chunk` bytes: chunk_number, part and chunks, their number; a revisit has one empty chunk."""
    kept = F.when(F.col("record_type") == "revisit", 0).otherwise(F.col("size"))
    count = F.greatest(F.ceil(kept / float(chunk)), F.lit(1)).cast("int")
    parts = F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.substring(F.col("payload"), i * chunk + 1, F.when(F.col("record_type") == "revisit", 0).otherwise(chunk)))
    names = [c for c in pages.columns if c != "payload"]
    numbered = pages.withColumn("row", F.monotonically_increasing_id())
    return numbered.select(*names, "row", count.alias("chunks"), F.posexplode(parts).alias("chunk_number", "part"))


def segments(part: bytes) -> Iterator[bytes]:
    """A chunk cut inside every version line that it holds, so that no segment can complete a record mark."""
    at = 0
    while True:
        mark = part.find(VERSION, at)
        to = len(part) if mark < 0 else mark + 2
        yield part[at:to]
        at = to
        if mark < 0 or at >= len(part):
            return


def _head(kind: str, name: str, fields: list[str], block: bytes) -> bytes:
    lines = [f"WARC-Type: {kind}", f"WARC-Date: {DATE}", f"WARC-Record-ID: {name}", *fields, f"Content-Length: {len(block)}"]
    return VERSION + LINE + "\r\n".join(lines).encode() + RECORD_END + block


def archive_records(pages: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """record, chunk_number, running_digest and value, the bytes of one archive record without its end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds, names = [pa.string(), pa.int32(), pa.string(), pa.binary()], ["record", "chunk_number", "running_digest", "value"]
        out: list[tuple] = []
        held, digest, number, opened = 0, hashlib.sha256(), 0, False

        def batch_of(rows: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows) if rows else [()] * 4, kinds, strict=True)], names)

        for batch in batches:
            columns = [batch.column(c) for c in ("page_id", "url", "digest", "size", "record_type", "refers_to", "named", "row", "chunks", "chunk_number", "part")]
            for i in range(batch.num_rows):
                page, url, whole, size, kind, refers, named, row, count, nth, part = (c[i].as_py() for c in columns)
                name = record_name(page, whole if named and kind == "response" else row)
                if not opened:
                    info, opened = b"software: kinetrace\r\nformat: WARC File Format 1.1\r\n", True
                    about = f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'file:{name}')}>"
                    out.append((about, 0, hashlib.sha256(info).hexdigest(), _head("warcinfo", about, ["Content-Type: application/warc-fields"], info)))
                if nth == 0:
                    digest, number = hashlib.sha256(), 0
                cut = [*segments(part)]
                for j, piece in enumerate(cut):
                    digest.update(piece)
                    running, last = digest.copy().hexdigest(), nth == count - 1 and j == len(cut) - 1
                    block, head = (HTTP + piece if number == 0 else piece), ["Page-Id: " + ("" if page is None else str(page))]
                    if number == 0:
                        if url is not None:
                            head.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
                        head += ["Content-Type: application/http; msgtype=response", f"WARC-Payload-Digest: sha256:{whole}", f"Payload-Length: {size}"]
                        if kind == "revisit":
                            head += [f"WARC-Refers-To: {record_name(refers, whole)}"] * named + [f"Refers-To-Page: {refers}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
                    if number or not last:
                        head += [f"WARC-Segment-Number: {number + 1}", f"Running-Digest: {running}"]
                        if number:
                            head.append(f"WARC-Segment-Origin-ID: {name}")
                        if last:
                            head.append(f"WARC-Segment-Total-Length: {size + len(HTTP)}")
                    own = name if number == 0 else f"{name[:-1]}-{number}>"
                    out.append((name, number, running, _head(kind if number == 0 else "continuation", own, head, block)))
                    number, held = number + 1, held + len(piece)
                    if held > 4 * chunk:
                        yield batch_of(out)
                        out, held = [], 0
        yield batch_of(out)

    return chunk_rows(pages, chunk).mapInArrow(run, "record string, chunk_number int, running_digest string, value binary")


def write_archive(pages: DataFrame, path: str, chunk: int = CHUNK, compression: str = "none") -> str:
    """Writes the pages that `classified` gives as an archive folder."""
    archive_records(pages, chunk).select(F.col("value").cast("string").alias("value")).write.option("lineSep", RECORD_END.decode()).option("compression", compression).text(path)
    return path


def read_chunks(spark: SparkSession, path: str) -> DataFrame:
    """The archive's chunk table: record, chunk_number, last, page_id, record_type, refers_to, stated_bytes, stated_digest, payload."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.string(), pa.int32(), pa.bool_(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
        names = ["record", "chunk_number", "last", "page_id", "record_type", "refers_to", "stated_bytes", "stated_digest", "payload"]
        for batch in batches:
            rows = []
            for raw in batch.column("value"):
                data = raw.as_py()
                if data.startswith(VERSION):
                    data = data[len(VERSION) + 2 :]
                if not data:
                    continue
                head, _, block = data.partition(RECORD_END)
                fields = dict(x.split(": ", 1) for x in head.decode().split("\r\n") if ": " in x)
                if fields["WARC-Type"] == "warcinfo":
                    continue
                block = block[: int(fields["Content-Length"])]
                number = int(fields.get("WARC-Segment-Number", 1)) - 1
                kind = fields["WARC-Type"]
                if number == 0:
                    block = block.partition(RECORD_END)[2]
                split = "WARC-Segment-Number" in fields
                page = fields.get("Page-Id", "").strip()
                rows.append((
                    fields.get("WARC-Segment-Origin-ID", fields["WARC-Record-ID"]), number, not split or "WARC-Segment-Total-Length" in fields, int(page) if page else None, kind,
                    int(fields["Refers-To-Page"]) if fields.get("Refers-To-Page", "None") != "None" else None, int(fields["Payload-Length"]) if number == 0 else None,
                    fields.get("WARC-Payload-Digest", "")[7:] or None, block,
                ))
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows) if rows else [()] * len(kinds), kinds, strict=True)], names)

    lines = spark.read.option("lineSep", MARK.decode()).text(path).select(F.col("value").cast("binary").alias("value"))
    return lines.mapInArrow(run, "record string, chunk_number int, last boolean, page_id bigint, record_type string, refers_to bigint, stated_bytes bigint, stated_digest string, payload binary")


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of every record, digests made from the bytes read.

    Records of one chunk are hashed where they are read; only the chunks of oversized ones are dealt by record."""
    rows = read_chunks(spark, path)
    single = F.col("last") & (F.col("chunk_number") == 0)
    kept = rows.withColumn("digest", F.when(single & (F.col("record_type") == "response"), F.sha2("payload", 256))).withColumn("bytes", F.octet_length("payload").cast("bigint"))
    slim = kept.withColumn("payload", F.when(~single, F.col("payload")))
    dealt = slim.repartition("record").sortWithinPartitions("record", "chunk_number")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_: dict | None = None
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                if row["chunk_number"] == 0:
                    open_ = row | {"hash": hashlib.sha256(), "bytes": 0} if not row["last"] else None
                    if row["last"]:
                        revisit = row["record_type"] == "revisit"
                        out.append((row["page_id"], row["stated_bytes"] if revisit else row["bytes"], row["stated_digest"] if revisit else row["digest"], row["record_type"], row["refers_to"]))
                        continue
                open_["hash"].update(row["payload"])
                open_["bytes"] += len(row["payload"])
                if row["last"]:
                    out.append((open_["page_id"], open_["bytes"], open_["hash"].hexdigest(), open_["record_type"], open_["refers_to"]))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*out) if out else [()] * 5, kinds, strict=True)], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    return dealt.mapInArrow(run, "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint")


def round_trip(pages: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """Every page written to an archive in shared storage and read back."""
    path = fresh_path(pages.sparkSession, "warc")
    return read_archive(pages.sparkSession, write_archive(classified(pages), path, chunk))


ORACLE_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes, sha256(h) AS payload_digest, min(page_id) OVER (PARTITION BY h) AS first FROM p)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= 100 AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id <> first THEN first END AS refers_to FROM d
"""
