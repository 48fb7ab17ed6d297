"""WARC archives with revisit records, and their resolution.

Headers are shuffled by payload digest, repeats are joined to the first record of their payload, and the archives
are written anew: one response per payload, revisits that refer to it by record id, address and date.  Archives are read
a record at a time, by their Content-Length, so that a payload may hold anything; a file may be one gzip member or have
one for each record, as is usual, or be plain.  Gzip files come to a task in pieces, so that their size doesn't matter.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from itertools import groupby
from operator import itemgetter

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, join_split, materialise, scratch, ship

# Fixed values of the format.
VERSION = "WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"

LEAST_BYTES = 100
RECORDS_PER_FILE = 4000


def record_id(page: Column, url: Column) -> Column:
    """A urn:uuid made of the page's id and address."""
    h = F.md5(F.concat_ws("\x1f", F.coalesce(page.cast("string"), F.lit("")), F.coalesce(url, F.lit(""))))
    parts = [F.substring(h, at, n) for at, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]
    return F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *parts), F.lit(">"))


def _address(url: Column) -> Column:
    return F.regexp_replace(F.coalesce(url, F.lit("about:blank")), r"\s", "%20")


def mark_revisits(pages: DataFrame, digest: str = "digest", size: str = "payload_bytes", key: str = "page_id", url: str = "url", least: int = LEAST_BYTES) -> DataFrame:
    """pages with refers_to and refers_url (key and address of the record with the smallest key of the same payload, null
    where the row is that record itself), for payloads of at least `least` bytes.

    The first record of each repeated payload comes from a partial aggregation, which a hot payload doesn't skew; of
    repeated rows with the smallest key the first address by order is referred to.  In the join back the rows of very
    common payloads are dealt over parts."""
    d, first = fresh("digest"), fresh("first")
    long = F.when(F.col(size) >= least, F.col(digest))
    place = F.when(F.col(key).isNotNull(), F.struct(F.col(key).alias("key"), F.col(url).alias("url")))
    found = pages.groupBy(long.alias(d)).agg(F.min(place).alias(first), F.count(F.lit(1)).alias("n"))
    found = materialise(found.filter(f"n > 1 and `{d}` is not null and `{first}` is not null"), "payloads")
    joined = join_split(pages.withColumn(d, long), found.select(d, first), [d], found.select(d, "n"), F.xxhash64(key, url), "left")
    repeat = ~F.col(key).eqNullSafe(F.col(f"{first}.key")) & F.col(first).isNotNull()
    return joined.withColumns({"refers_to": F.when(repeat, F.col(f"{first}.key")), "refers_url": F.when(repeat, F.col(f"{first}.url"))}).drop(d, first)


def to_records(pages: DataFrame) -> DataFrame:
    """pages (page_id, url, html, refers_to, refers_url, digest, payload_bytes) to the text of one record each, without its last line feed."""
    eol = "\r\n"
    revisit = F.col("refers_to").isNotNull()
    payload = F.when(revisit, F.lit("")).otherwise(F.coalesce("html", F.lit("")))
    id_of = F.coalesce(F.col("page_id").cast("string"), F.lit("-"))
    refers = F.concat(
        F.lit(f"{eol}WARC-Profile: {PROFILE}{eol}WARC-Refers-To: "), record_id(F.col("refers_to"), F.col("refers_url")),
        F.lit(f"{eol}WARC-Refers-To-Target-URI: "), _address(F.col("refers_url")),
        F.lit(f"{eol}WARC-Refers-To-Date: {DATE}"),
    )
    head = F.concat(
        F.lit(f"{VERSION}{eol}WARC-Type: "), F.when(revisit, "revisit").otherwise("response"),
        F.lit(f"{eol}WARC-Record-ID: "), record_id(F.col("page_id"), F.col("url")),
        F.lit(f"{eol}WARC-Date: {DATE}{eol}WARC-Target-URI: "), _address(F.col("url")),
        F.lit(f"{eol}WARC-Payload-Digest: sha256:"), F.col("digest"),
        F.lit(f"{eol}X-Page-Id: "), id_of,
        F.when(revisit, refers).otherwise(F.lit("")),
        F.lit(f"{eol}Content-Type: text/html; charset=utf-8{eol}Content-Length: "), F.octet_length(payload).cast("string"),
        F.lit(f"{eol}{eol}"),
    )
    return F.concat(head, payload, F.lit("\r\n\r")).alias("value")


def write_archives(pages: DataFrame, path: str, records_per_file: int = RECORDS_PER_FILE) -> None:
    """Gzip archives of up to records_per_file records; Spark's writer commits them."""
    pages.select(to_records(pages)).write.option("maxRecordsPerFile", records_per_file).option("compression", "gzip").text(path)


_BLANK = b"\r\n\r\n"
_HEADER = re.compile(rb"([\w-]+):[ \t]*([^\r\n]*)\r\n")


def unpacked(data: bytes, step: int = 1 << 20) -> Iterator[bytes]:
    """The bytes of all gzip members of a file in pieces of at most `step`, or the file's own if it isn't compressed."""
    import zlib

    if data[:2] != b"\x1f\x8b":
        yield data
        return
    rest = memoryview(data)
    while len(rest) and bytes(rest[:2]) == b"\x1f\x8b":
        member, piece = zlib.decompressobj(31), rest
        while not member.eof:
            out = member.decompress(piece, step)
            if not out and not member.unconsumed_tail and not member.eof:
                raise ValueError("a gzip member ends early")
            piece = member.unconsumed_tail
            yield out
        rest = rest[len(rest) - len(member.unused_data) :]


def parse(pieces: Iterator[bytes]) -> Iterator[tuple[dict[bytes, bytes], bytes]]:
    """(headers, block) of each record of an archive that comes in pieces; one record and a piece are held."""
    held, done = bytearray(), False
    pieces = iter(pieces)

    def have(n: int) -> bool:
        nonlocal done
        while len(held) < n and not done:
            piece = next(pieces, None)
            done = piece is None
            held.extend(piece or b"")
        return len(held) >= n

    at = 0
    while have(1):
        end = held.find(b"\r\n\r\n")
        while end < 0 and have(len(held) + 1):
            end = held.find(b"\r\n\r\n")
        if not held.startswith(b"WARC/") or end < 0:
            raise ValueError(f"no WARC record at byte {at}")
        headers = {k.lower(): v.strip() for k, v in _HEADER.findall(held, 0, end + 2)}
        start = end + 4
        stop = start + int(headers[b"content-length"])
        if not have(stop + 4) or held[stop : stop + 4] != b"\r\n\r\n":
            raise ValueError(f"the record at byte {at} does not end as it should")
        yield headers, bytes(held[start:stop])
        at += stop + 4
        del held[: stop + 4]


READ = "page_id bigint, record_id string, record_type string, url string, digest string, payload_bytes bigint, refers_to string, refers_url string, payload binary"


def read_archives(spark, path: str, payloads: bool = False, pattern: str = "*.gz") -> DataFrame:
    """A row per response, resource or revisit record of the archives under path, their own or foreign ones: digests and
    sizes are those of the bytes read, for revisits the header's digest; refers_to is the record id that a revisit names.

    Files whose pattern ends in .gz come in pieces, others whole.  page_id is null in archives that were not written here.  An HTTP response's own header isn't part of its payload."""
    ship(spark)
    whole = not pattern.endswith(".gz")
    if whole:
        files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(path).select("content", F.xxhash64("path").alias("file"))
    else:  # no reader splits a gzip file, so one task has its pieces in their order
        text = spark.read.option("lineSep", _BLANK.decode()).option("pathGlobFilter", pattern).text(path)
        files = text.select(F.col("value").cast("binary"), F.xxhash64(text.metadataColumn("_metadata")["file_path"]).alias("file"))
    kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.binary()]
    names = ["page_id", "record_id", "record_type", "url", "digest", "payload_bytes", "refers_to", "refers_url", "payload"]
    told = lambda h, name: h[name].decode("utf-8", "replace") if name in h else None

    def row(h: dict[bytes, bytes], block: bytes) -> tuple:
        kind, page = h[b"warc-type"].decode(), h.get(b"x-page-id", b"-")
        own = kind != "revisit"
        if own and h.get(b"content-type", b"").startswith(b"application/http"):
            block = block.partition(b"\r\n\r\n")[2]
        digest = hashlib.sha256(block).hexdigest() if own else (told(h, b"warc-payload-digest") or "").removeprefix("sha256:")
        return (int(page) if page != b"-" else None, told(h, b"warc-record-id"), "response" if own else kind, told(h, b"warc-target-uri"), digest, len(block) if own else None, told(h, b"warc-refers-to"), told(h, b"warc-refers-to-target-uri"), block if own and payloads else None)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = ((file, piece.as_py()) for batch in batches for piece, file in zip(batch.column(0), batch.column(1).to_pylist()))
        out, size = [], 0
        for _, mine in groupby(pieces, itemgetter(0)):
            for h, block in parse(unpacked(next(mine)[1]) if whole else (piece + _BLANK for _, piece in mine)):
                if h[b"warc-type"] in (b"response", b"resource", b"revisit"):
                    out.append(row(h, block))
                    size += len(block) * payloads
                if len(out) >= 2000 or size > 1 << 25:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=names)
                    out, size = [], 0
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=names)

    return files.mapInArrow(run, READ)


def resolve(records: DataFrame) -> DataFrame:
    """Revisit records joined to the responses that hold their payload: page_id, payload_bytes, payload_digest, record_type,
    refers_to (the response's page), record_id, refers_to_record.

    A revisit names its response by record id, or by address and digest where it gives no id, as older archives do.  One
    whose response is nowhere in the archives keeps null payload_bytes and refers_to.  Only responses that some revisit
    names are joined, and the revisits of very common ones are dealt over parts."""
    held = records.filter("record_type = 'response'")
    revisits = records.filter("record_type <> 'response'")
    name = F.coalesce("refers_to", F.concat_ws("\x1f", F.coalesce("refers_url", "url"), "digest"))
    revisits = revisits.withColumn("name", name)
    counts = materialise(revisits.groupBy("name").agg(F.count(F.lit(1)).alias("n")), "named")
    by = lambda name: held.select(name.alias("name"), F.struct(F.col("page_id").alias("page"), F.col("payload_bytes").alias("size"), F.col("digest").alias("digest"), F.col("record_id").alias("record")).alias("r"))
    both = by(F.col("record_id")).union(by(F.concat_ws("\x1f", "url", "digest")))
    found = both.join(counts.select("name"), "name", "left_semi").groupBy("name").agg(F.min("r").alias("r"))
    joined = join_split(revisits, found, ["name"], counts, F.xxhash64("page_id", "record_id"), "left")
    plain = held.select("page_id", "payload_bytes", F.col("digest").alias("payload_digest"), "record_type", F.lit(None).cast("bigint").alias("refers_to"), "record_id", F.lit(None).cast("string").alias("refers_to_record"))
    digest = F.coalesce(F.col("r.digest"), F.col("digest"))
    return plain.unionByName(joined.select("page_id", F.col("r.size").alias("payload_bytes"), digest.alias("payload_digest"), "record_type", F.col("r.page").alias("refers_to"), "record_id", F.col("r.record").alias("refers_to_record")))


def deduplicated_archives(pages: DataFrame, path: str | None = None, key: str = "page_id", url: str = "url", html: str = "html", least: int = LEAST_BYTES) -> str:
    """Write the pages as WARC archives in which each payload of at least `least` bytes stands once; return the path.

    Null html is an empty payload, which like all short ones is a response of its own.  A null key never is the
    record that others refer to.  Repeated rows with the smallest key of their payload are all responses, so there are no
    ties.  An empty table gives archives without records.  Other columns are not read.  A file has up to
    RECORDS_PER_FILE records whatever their bytes; very long pages make large files, which are read in pieces."""
    path = path or scratch(pages.sparkSession, "warc")
    payload = F.coalesce(F.col(html).cast("string"), F.lit(""))
    rows = pages.select(F.col(key).cast("bigint").alias("page_id"), F.col(url).cast("string").alias("url"), payload.alias("html"))
    rows = rows.withColumns({"digest": F.sha2(F.encode("html", "UTF-8"), 256), "payload_bytes": F.octet_length("html").cast("bigint")})
    write_archives(mark_revisits(rows, least=least), path)
    return path


def pages_by_archives(pages: DataFrame, **names) -> DataFrame:
    """Write the pages to deduplicated archives, read these back and resolve the revisits: one row per page."""
    path = deduplicated_archives(pages, **names)
    return resolve(read_archives(pages.sparkSession, path)).drop("record_id", "refers_to_record")
