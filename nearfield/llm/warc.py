"""WARC archives: writing captures as request, response (or revisit) and metadata records, reading them back, and
assembling the records of each transaction through their concurrent-to identifiers into one row per capture.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import cut, plain, remove_folder, shared_folder, tidy
from .token_files import put

#: Compressed bytes of an archive, about; one larger capture makes a larger one.
FILE_BYTES = 24 << 20
#: Fixed values of the format.
DATE, PROFILE = "2024-01-01T00:00:00Z", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_RECORD = "record_id string, type string, concurrent_to string, refers_to string, target_uri string, digest string, payload_bytes long, fields map<string,string>, file string, offset long"


def record(kind: str, record_id: str, headers: dict[str, str], block: bytes, content_type: str) -> bytes:
    """One record as a gzip member."""
    head = {"WARC-Type": kind, "WARC-Record-ID": f"<{record_id}>", "WARC-Date": DATE, **headers, "Content-Type": content_type, "Content-Length": str(len(block))}
    data = b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode() + b"\r\n" + block + b"\r\n\r\n"
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def clean(value: str | None) -> str:
    """A header's value: without line ends."""
    return " ".join((value or "").split())


def capture_records(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, n: str) -> bytes:
    """The records of one page: request, response or revisit, metadata."""
    digest = hashlib.sha1(payload).hexdigest()
    anchor, uri = f"urn:capture:{'null' if page_id is None else page_id}:{n}", clean(url)
    common = {"WARC-Target-URI": uri} if uri else {}
    host = uri.split("/")[2] if uri.count("/") >= 2 else ""
    request = f"GET {uri or '/'} HTTP/1.1\r\nHost: {host}\r\n\r\n".encode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    own = common | {"WARC-Payload-Digest": f"sha1:{digest}"}
    if refers_to is None:
        main = record("response", anchor, own, http + payload, "application/http;msgtype=response")
    else:
        own |= {"WARC-Profile": PROFILE, "WARC-Refers-To": f"<urn:capture:{refers_to}>"}
        main = record("revisit", anchor, own, http, "application/http;msgtype=response")
    beside = common | {"WARC-Concurrent-To": f"<{anchor}>"}
    meta = f"page-id: {'' if page_id is None else page_id}\r\nhas-url: {int(url is not None)}\r\n".encode()
    return (
        record("request", anchor + ":request", beside, request, "application/http;msgtype=request")
        + main
        + record("metadata", anchor + ":metadata", beside, meta, "application/warc-fields")
    )


def write_archives(pages: DataFrame, folder: str, least: int = 1000) -> DataFrame:
    """Write one capture per row of (page_id, url, html); returns (file, captures).

    Of rows with equal payloads of at least ``least`` bytes, those with the largest page_id are responses and the
    others revisits of it; smaller ones are all responses. Null html is an empty payload; null page_ids are below all
    others. Rows that share page_id and payload are captures each. Other columns are ignored.

    A file's name holds the attempt that wrote it, and the rows returned name the files of the attempts that Spark
    took: files of a lost or repeated attempt may be left in the folder and are no part of the archive.
    """
    rows = pages.select("page_id", "url", plain("html").alias("html"))
    payload = F.encode("html", "UTF-8")
    large = pages.select("page_id", payload_of("html").alias("bytes")).where(F.octet_length("bytes") >= least).select("page_id", F.sha1("bytes").alias("digest"))
    best = large.groupBy("digest").agg(F.max("page_id").alias("original"), F.count(F.lit(1)).alias("n")).where("n > 1 and original is not null")
    best = best.select(F.col("digest").alias("_digest"), "original")
    rows = rows.withColumn("digest", F.when(F.octet_length(payload) >= least, F.sha1(payload)).otherwise(F.concat(F.lit("small "), F.xxhash64("page_id").cast("string"))))
    rows = rows.join(best, F.col("digest") == F.col("_digest"), "left")
    revisits = F.when(F.col("page_id").isNull() | (F.col("page_id") < F.col("original")), F.col("original"))

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, attempt, number, at, size = TaskContext.get().partitionId(), uuid.uuid4().hex[:12], 0, 0, 0
        held: list[bytes] = []
        files: list[tuple[str, int]] = []

        def flush() -> None:
            nonlocal number, size
            put(folder, name := f"part-{part:06d}-{number:06d}-{attempt}.warc.gz", b"".join(held))
            files.append((name, len(held)))
            held.clear()
            number, size = number + 1, 0

        for b in batches:
            for page, url, html, refers in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).cast(pa.binary()).to_pylist(), b.column(3).to_pylist(), strict=True):
                held.append(capture_records(page, url, html, refers, f"{part}-{at}"))
                at, size = at + 1, size + len(held[-1])
                if size >= FILE_BYTES:
                    flush()
        if held:
            flush()
        yield pa.RecordBatch.from_pydict({"file": pa.array([f for f, _ in files], pa.string()), "captures": pa.array([n for _, n in files], pa.int64())})

    return cut(rows.select("page_id", "url", "html", revisits.alias("refers")).mapInArrow(tidy(write), "file string, captures long"))


def payload_of(column: str):
    return F.encode(plain(column), "UTF-8")


def members(data: bytes) -> Iterator[tuple[int, bytes]]:
    """(offset, content) of each gzip member."""
    at = 0
    view = memoryview(data)
    while at < len(data):
        z = zlib.decompressobj(31)
        # members are small against an archive, so look at growing windows of it
        size, out = 1 << 16, []
        place = at
        while not z.eof:
            if place >= len(data):
                raise ValueError(f"the archive ends within the record at byte {at}")
            out.append(z.decompress(view[place : place + size]))
            place = min(place + size, len(data))
        yield at, b"".join(out)
        at = place - len(z.unused_data)


def parse(content: bytes) -> tuple[dict[str, str], bytes]:
    """(headers, block) of one record; header names in lower case."""
    head, _, rest = content.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    return headers, rest[: int(headers.get("content-length", 0))]


def _bare(v: str | None) -> str | None:
    return v.strip("<>") if v else None


def read_records(spark: SparkSession, folder: str, files: DataFrame | None = None) -> DataFrame:
    """A row per record: ids and links, target, payload digest and length, other fields, file and offset.

    ``files``: only records of the files that its column ``file`` names, as ``write_archives`` returns them; without
    it, of all archives of the folder.

    The digest of a response is computed from the payload read and must equal its header; a revisit has no payload,
    so its digest is the header's and its length that of its HTTP header.
    """

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                rows = []
                for offset, content in members(data):
                    h, block = parse(content)
                    kind = h.get("warc-type")
                    digest, size, fields = (h.get("warc-payload-digest") or "").removeprefix("sha1:") or None, None, {}
                    if kind in ("response", "revisit"):
                        http, _, payload = block.partition(b"\r\n\r\n")
                        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in http.decode("utf-8", "replace").split("\r\n")[1:])}
                        size = len(payload) if kind == "response" else int(fields["content-length"])
                        if kind == "response" and hashlib.sha1(payload).hexdigest() != digest:
                            raise ValueError(f"{path}, byte {offset}: the payload does not have its digest")
                    elif kind == "metadata":
                        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in block.decode("utf-8", "replace").split("\r\n") if x)}
                    rows.append((_bare(h.get("warc-record-id")), kind, _bare(h.get("warc-concurrent-to")), _bare(h.get("warc-refers-to")), h.get("warc-target-uri"), digest, size, list(fields.items()), path.rpartition("/")[2], offset))
                s, i = pa.string(), pa.int64()
                kinds = (s, s, s, s, s, s, i, pa.map_(s, s), s, i)
                names = [x.split()[0] for x in _RECORD.replace("map<string,string>", "m").split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    content = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(folder).select("path", "content")
    found = content.mapInArrow(tidy(read), _RECORD)
    return found if files is None else found.join(files.select("file"), "file", "left_semi").select(*found.columns)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: capture_id and the structs response (or revisit), request and metadata.

    A record belongs to the transaction that its concurrent-to names, or else to its own; records that name each
    other's companions in any file meet by that identifier in one shuffle. Missing companions are null; of several of
    a kind the first by record id is taken. Transactions without a response or revisit are kept, with a null one.
    """
    one = F.struct("record_id", "type", "refers_to", "target_uri", "digest", "payload_bytes", "fields", "file", "offset")
    kind = lambda *k: F.min_by(F.when(F.col("type").isin(*k), one), F.when(F.col("type").isin(*k), F.col("record_id")))
    keyed = records.withColumn("capture_id", F.coalesce("concurrent_to", "record_id"))
    return keyed.groupBy("capture_id").agg(kind("response", "revisit").alias("response"), kind("request").alias("request"), kind("metadata").alias("metadata"))


def captures(pages: DataFrame, folder: str | None = None, least: int = 1000) -> DataFrame:
    """Write the pages' archives, read them back and assemble: see ``write_archives``, ``read_records``, ``assemble``.

    Without ``folder`` the archives are a passing step: the captures are cut and the archives removed.
    """
    spark = pages.sparkSession
    own = folder or shared_folder(spark, "warc")
    files = write_archives(pages, own, least)
    if files.isEmpty():
        return assemble(spark.createDataFrame([], _RECORD))
    found = assemble(read_records(spark, own, files))
    if folder is None:
        found = cut(found)
        remove_folder(spark, own)
    return found


def digest_rows(nested: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to (the response's page_id) of assembled captures."""
    r = F.col("response")
    page = F.nullif(F.element_at(F.col("metadata.fields"), "page-id"), F.lit("")).cast("long")
    refers = F.nullif(F.substring_index(r.refers_to, ":", -1), F.lit("")).cast("long")
    return nested.select(page.alias("page_id"), r.payload_bytes.alias("payload_bytes"), r.digest.alias("payload_digest"), r.type.alias("record_type"), F.when(r.type == "revisit", refers).alias("refers_to"))
