"""WARC archives, each record a Zstandard frame with a shared dictionary.

An archive opens with a skippable frame that holds its dictionary, trained on the
archive's own records; each record is one frame, so records can be read alone.
Of records with equal payloads that with the largest id is the response and the
others are revisits that name it.

Archives are rows of a table (name, bytes) in the shared folder, which Spark can
write to and read from any store; :func:`export_archives` and
:func:`read_archive_files` exchange them with ``.warc.zst`` files.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.llm.worker_cache import released
from reuse_engine.storage import few_broadcast, join_few, materialize, spread

#: Fixed values of the formats: skippable frame of a dictionary, and the profile of a revisit.
DICTIONARY_MAGIC = 0x184D2A5D
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"

ARCHIVE_BYTES = 32 << 20
DICTIONARY_BYTES, SAMPLE_BYTES = 64 << 10, 4 << 20
LEVEL = 3
DATE = "2026-01-01T00:00:00Z"
#: Payloads of at least so many bytes are deduplicated.
MIN_REVISIT_BYTES = 0


#: Bytes of an archive that are handed to the decompressor at one time.
READ_BYTES = 16 << 10


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_urn(page_id: int | None, url: str | None, digest: str) -> str:
    """Name of a record; only rows that are equal in all three share one."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id}\n{digest}\n{url}')}>"


def _line(value: str) -> str:
    """Header values stay on one line."""
    return value.replace("%", "%25").replace("\r", "%0D").replace("\n", "%0A")


def _unline(value: str) -> str:
    return value.replace("%0A", "\n").replace("%0D", "\r").replace("%25", "%")


def record(page_id: int | None, url: str | None, payload: bytes, target: str | None, digest: str, date: str = DATE) -> bytes:
    """One WARC/1.1 record; ``target``, the name of a response with an equal payload, makes a revisit.

    ``X-Page-ID`` is the only private field: the key of the row that was written.
    """
    block = HTTP if target else HTTP + payload
    head = [
        ("WARC-Type", "revisit" if target else "response"),
        ("WARC-Record-ID", record_urn(page_id, url, digest)),
        ("WARC-Date", date),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("Content-Type", "application/http; msgtype=response"),
    ]
    if url is not None:
        head.append(("WARC-Target-URI", _line(url)))
    if page_id is not None:
        head.append(("X-Page-ID", str(page_id)))
    if target:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", target)]
    head.append(("Content-Length", str(len(block))))
    text = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head) + "\r\n"
    return text.encode("utf-8", "surrogatepass") + block + b"\r\n\r\n"


def parse_record(data: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields and block of a record."""
    head, _, rest = data.partition(b"\r\n\r\n")
    version, *lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not version.startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines)
    block = rest[: int(fields["Content-Length"])]
    if len(block) != int(fields["Content-Length"]):
        raise ValueError("a WARC record is cut off")
    return fields, block


def pack(records: list[bytes], level: int = LEVEL) -> bytes:
    """An archive of records: dictionary frame, then a frame each."""
    total = sum(map(len, records))
    step = max(1, -(-total // SAMPLE_BYTES))
    samples = records[::step]
    try:
        trained = zstandard.train_dictionary(min(DICTIONARY_BYTES, max(1024, total // 8)), samples, k=512, d=8, level=level).as_bytes()
    except zstandard.ZstdError:  # too few or too small records to train on
        trained = b""
    out = [struct.pack("<II", DICTIONARY_MAGIC, len(trained)), trained]
    made = zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(trained), write_content_size=True) if trained else zstandard.ZstdCompressor(level=level)
    out += [made.compress(r) for r in records]
    return b"".join(out)


def unpack(archive: bytes) -> Iterator[bytes]:
    """Records of an archive in order."""
    magic, size = struct.unpack_from("<II", archive)
    if magic != DICTIONARY_MAGIC:
        raise ValueError("an archive starts with its dictionary")
    trained = archive[8 : 8 + size]
    reader = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(trained)) if trained else zstandard.ZstdDecompressor()
    whole, at = memoryview(archive), 8 + size
    while at < len(whole):
        frame, parts = reader.decompressobj(), []
        while not frame.eof:
            piece = whole[at : at + READ_BYTES]
            if not len(piece):
                raise ValueError("an archive is cut off")
            parts.append(frame.decompress(piece))
            at += len(piece) - len(frame.unused_data)  # what is left of one piece, not of the archive
        yield b"".join(parts)


@released
def _archive(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[bytes] = []
    size = 0

    def row() -> pa.RecordBatch:
        data = pack(held)
        name = f"{hashlib.sha1(data).hexdigest()}.warc.zst"
        return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([data], pa.binary()), pa.array([len(held)], pa.int64())], names=["name", "data", "records"])

    for batch in batches:
        for page, url, html, hexed, first_id, first_url in zip(*[c.to_pylist() for c in batch.columns], strict=True):
            digest = base64.b32encode(bytes.fromhex(hexed)).decode()
            revisits = page is not None and first_id is not None and page != first_id
            held.append(record(page, url, html or b"", record_urn(first_id, first_url, digest) if revisits else None, digest))
            size += len(held[-1])
            if size >= ARCHIVE_BYTES:
                yield row()
                held, size = [], 0
    if held:
        yield row()


def write_archives(pages: DataFrame, min_bytes: int = MIN_REVISIT_BYTES) -> DataFrame:
    """(name, data, records): archives of all rows of ``pages`` (page_id, url, html).

    Null html is an empty payload; null url has no target; rows that repeat an id
    and a payload are responses each, as are rows without an id.  Payloads below
    ``min_bytes`` are always responses.  Equal payloads are found by SHA-1, whose
    groups are pre-aggregated; only digests of several rows are joined back, by
    broadcast or with a salt, so that a common payload is dealt over many tasks.
    """
    body = F.coalesce(F.col("html").cast("binary"), F.lit(b""))
    rows = spread(pages.select(F.col("page_id").cast("long").alias("page_id"), "url", body.alias("html"))).withColumn("digest", F.sha1("html"))
    able = pages.select(F.struct(F.col("page_id").cast("long").alias("page_id"), "url").alias("row"), body.alias("html"))
    able = able.where((F.length("html") >= min_bytes) & F.col("row.page_id").isNotNull())
    groups = able.select("row", F.sha1("html").alias("digest")).groupBy("digest").agg(F.max("row").alias("first"), F.count("*").alias("n"))
    twice = materialize(groups.where("n > 1").select("digest", F.col("first.page_id").alias("first_id"), F.col("first.url").alias("first_url")), "warc-twice")
    named = join_few(rows, twice, "digest", F.xxhash64("page_id", "url"), "left").select("page_id", "url", "html", "digest", "first_id", "first_url")
    return materialize(named.mapInArrow(_archive, "name string, data binary, records long"), "warc-archives")


_RECORD = "record_id string, page_id long, url string, payload_bytes long, payload_digest string, record_type string, target string, intact boolean"


@released
def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [f.split()[0] for f in _RECORD.split(", ")]
    kinds = [pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.bool_()]
    for batch in batches:
        for data in batch.column(batch.schema.get_field_index("data")).to_pylist():
            out = []
            for raw in unpack(data):
                f, block = parse_record(raw)
                page, url, stated = f.get("X-Page-ID"), f.get("WARC-Target-URI"), f["WARC-Payload-Digest"].removeprefix("sha1:")
                row = [f["WARC-Record-ID"], None if page is None else int(page), None if url is None else _unline(url)]
                if f["WARC-Type"] == "revisit":
                    out.append((*row, None, stated, "revisit", f["WARC-Refers-To"], None))
                else:
                    payload = block.partition(b"\r\n\r\n")[2]
                    digest = base32_sha1(payload)
                    out.append((*row, len(payload), digest, f["WARC-Type"], None, digest == stated))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)


def read_archives(archives: DataFrame) -> DataFrame:
    """(record_id, page_id, url, payload_bytes, payload_digest, record_type, refers_to, intact) of each record.

    A response's length and digest are those of the payload that was read; a
    revisit's length, and the page it refers to, are those of the record that it
    names.  ``intact``: a response's payload has the digest that its header states;
    a revisit's target exists, is intact and has the stated digest.
    """
    records = materialize(archives.select("data").mapInArrow(_read, _RECORD), "warc-records")
    named = records.where("target is not null").select(F.col("target").alias("record_id")).distinct()
    targets = records.where("target is null").join(few_broadcast(named), "record_id", "left_semi").groupBy(F.col("record_id").alias("target")).agg(
        F.max("page_id").alias("refers_to"), F.max("payload_bytes").alias("target_bytes"), F.max("payload_digest").alias("target_digest"), F.min("intact").alias("target_intact")
    )
    both = join_few(records, materialize(targets, "warc-targets"), "target", F.xxhash64("record_id"), "left")
    whole = F.coalesce(F.col("target_intact") & (F.col("target_digest") == F.col("payload_digest")), F.lit(False))
    return both.select(
        "record_id", "page_id", "url", F.coalesce("payload_bytes", "target_bytes").alias("payload_bytes"), "payload_digest", "record_type", "refers_to",
        F.when(F.col("record_type") == "revisit", whole).otherwise(F.col("intact")).alias("intact"),
    )


def export_archives(archives: DataFrame, uri: str) -> DataFrame:
    """Write each archive as a file under ``uri``, a folder that all executors share; (name, bytes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(uri)
        store.create_dir(base, recursive=True)
        for batch in batches:
            names, datas = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for name, data in zip(names, datas, strict=True):
                with store.open_output_stream(f"{base}/{name}", compression=None) as out:
                    out.write(data)
            yield pa.RecordBatch.from_arrays([pa.array(names), pa.array([len(d) for d in datas], pa.int64())], names=["name", "bytes"])

    return archives.select("name", "data").mapInArrow(run, "name string, bytes long")


def read_archive_files(spark: SparkSession, path: str) -> DataFrame:
    """Records of the ``.warc.zst`` files under ``path``, in any store that Spark reads."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.zst").load(path)
    return read_archives(files.select(F.col("content").alias("data")))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return read_archives(write_archives(pages)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact")


def _sql_base32(hexed: str) -> str:
    """20 bits of a hexadecimal digest are four base32 letters."""
    bits = f"list_transform(range(8), lambda i: ('0x' || substr({hexed}, 5 * i + 1, 5))::INT)"
    letters = " || ".join(f"substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ((v >> {k}) & 31) + 1, 1)" for k in (15, 10, 5, 0))
    return f"array_to_string(list_transform({bits}, lambda v: {letters}), '')"


OP9_SQL = f"""
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS h FROM pages),
     g AS (SELECT h, max(page_id) AS first_id FROM p WHERE n >= {MIN_REVISIT_BYTES} GROUP BY h)
SELECT page_id, n AS payload_bytes, {_sql_base32("p.h")} AS payload_digest, CASE WHEN page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN page_id <> first_id THEN first_id END AS refers_to, true AS intact
FROM p LEFT JOIN g ON g.h = p.h
"""
