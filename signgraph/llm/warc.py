"""WARC: a deterministic sharded writer and a reader.

Records are range-sorted by page id, files roll by compressed size, each record is a gzip member with headers and
digests made anew, and a shard becomes visible in two steps: tasks write under temporary names that carry their attempt,
a manifest table records what the successful attempts wrote, then a second pass renames by that manifest. A lost task
leaves only a temporary file that no manifest names, and both passes can be repeated. Payloads of at least
`least` bytes that equal an earlier page's become revisit records.

Nulls: a null payload is empty, a null url or page id is left out of the headers. Repeated rows are repeated records: of equal
payloads, all rows of the smallest page id are responses; an id may stand on several payloads, each judged by itself. An empty table gives an empty archive. Extra columns are ignored.
"""
from __future__ import annotations

import gzip
import hashlib
import io
import uuid
import zlib

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_path, fresh_path

ROLL = 16 << 20
LEAST = 100
DATE = "2020-01-01T00:00:00Z"  # fixed, so that equal input gives equal files
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_MANIFEST = "shard int, part int, temp string, name string, records long, bytes long, sha256 string"
_PAGES = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def _urn(page_id: int | None, digest: str) -> str:
    """A version 8 UUID: the page id in the clear, the rest from the digest."""
    raw = bytearray((page_id or 0).to_bytes(8, "big", signed=True) + bytes.fromhex(digest[:16]))
    low = int.from_bytes(bytes(raw[8:]), "big") >> 6
    value = int.from_bytes(bytes(raw[:8]), "big")
    bits = (value >> 16) << 80 | 8 << 76 | (value >> 4 & 0xFFF) << 64 | 2 << 62 | (value & 15) << 58 | (low & (1 << 58) - 1)
    return f"<urn:uuid:{uuid.UUID(int=bits)}>"


def page_of(urn: str) -> int:
    """The page id inside a record id."""
    bits = uuid.UUID(urn.strip("<>").removeprefix("urn:uuid:")).int
    value = (bits >> 80) << 16 | (bits >> 64 & 0xFFF) << 4 | (bits >> 58 & 15)
    return value - (1 << 64) if value >> 63 else value


def record(page_id: int | None, url: str | None, payload: bytes, first: int | None) -> bytes:
    """One record; first is the page that a revisit refers to."""
    digest = hashlib.sha256(payload).hexdigest()
    body = b"" if first is not None else payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if first is None else 'revisit'}", f"WARC-Record-ID: {_urn(page_id, digest)}", f"WARC-Date: {DATE}"]
    if url is not None:
        head.append("WARC-Target-URI: " + "".join(c if c > " " else f"%{ord(c):02X}" for c in url))
    if page_id is not None:
        head.append(f"X-Page-ID: {page_id}")
    head += [f"WARC-Payload-Digest: sha256:{digest}", f"WARC-Block-Digest: sha256:{hashlib.sha256(body).hexdigest()}", f"X-Payload-Length: {len(payload)}"]
    if first is not None:
        head += [f"WARC-Refers-To: {_urn(first, digest)}", f"WARC-Profile: {PROFILE}"]
    head += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def pack(raw: bytes) -> bytes:
    """A gzip member without a time, so that it is the same each time."""
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def records(stream) -> object:
    """(headers, body) of each record of a file of gzip members; digests and lengths are checked."""
    f = gzip.GzipFile(fileobj=stream)
    while line := f.readline():
        if line != b"WARC/1.1\r\n":
            raise ValueError("no record here")
        head = {}
        while (line := f.readline()) != b"\r\n":
            key, _, value = line.decode().rstrip("\r\n").partition(": ")
            head[key.lower()] = value
        size = int(head["content-length"])
        body = f.read(size)
        if len(body) != size or f.read(4) != b"\r\n\r\n" or "sha256:" + hashlib.sha256(body).hexdigest() != head["warc-block-digest"]:
            raise ValueError("damaged record")
        yield head, body


def _fs(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else "file://" + path)


def _writer(folder: str, roll: int):
    def run(batches):
        ctx = TaskContext.get()
        part, attempt = ctx.partitionId(), ctx.taskAttemptId()
        store, base = _fs(folder)
        store.create_dir(base, recursive=True)
        out, made, n, size, shard, digest = None, [], 0, 0, 0, None
        held: tuple = (None, None, None)

        def close():
            nonlocal out, shard
            if out is not None:
                out.close()
                made.append((shard, part, temp, f"pages-{part:06d}-{shard:05d}.warc.gz", n, size, digest.hexdigest()))
                out, shard = None, shard + 1

        for b in batches:
            ids, digests, urls, pays, firsts, marks = (c for c in b.columns)
            for k in range(len(ids)):
                i, d = ids[k].as_py(), digests[k].as_py()
                if marks[k].as_py() == 0:  # the payload d of page i is a revisit; its rows come next
                    held = (i, d, firsts[k].as_py())
                    continue
                first = firsts[k].as_py() if i is None else held[2] if held[:2] == (i, d) else None
                raw = pack(record(i, urls[k].as_py(), pays[k].as_py() or b"", first))
                if out is None:
                    temp = f".{part:06d}-{shard:05d}-{attempt}.tmp"
                    out, n, size, digest = store.open_output_stream(f"{base}/{temp}", compression=None), 0, 0, hashlib.sha256()
                out.write(raw)
                digest.update(raw)
                n, size = n + 1, size + len(raw)
                if size >= roll:
                    close()
        close()
        cols = list(zip(*made, strict=True)) or [[]] * 7
        kinds = [pa.int32(), pa.int32(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=[x.split()[0] for x in _MANIFEST.split(", ")])

    return run


def _committer(folder: str):
    def run(batches):
        from pyarrow import fs

        store, base = _fs(folder)
        for b in batches:
            for temp, name in zip(b.column("temp").to_pylist(), b.column("name").to_pylist(), strict=True):
                if store.get_file_info(f"{base}/{temp}").type != fs.FileType.NotFound:
                    store.move(f"{base}/{temp}", f"{base}/{name}")
                elif store.get_file_info(f"{base}/{name}").type == fs.FileType.NotFound:
                    raise OSError(f"{name} is lost")
            yield b.select(["name", "records"])

    return run


def write_archive(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", least: int = LEAST, roll: int = ROLL) -> DataFrame:
    """Write pages as WARC shards below folder; returns the manifest, which lies in folder/_manifest.

    Which page is the response is found on digests alone (partial minima, then a join that may split hot digests); the
    revisits meet their pages, by id and digest, in the one range exchange that also sorts the records, so payloads are moved once.
    """
    spark = pages.sparkSession
    p = pages.select(F.col(id_col).cast("long").alias("i"), F.col(url_col).cast("string").alias("u"), F.coalesce(F.col(payload_col).cast("binary"), F.lit(b"")).alias("p")).withColumn("d", F.unhex(F.sha2("p", 256)))
    keys = p.where(F.octet_length("p") >= least).select("i", "d")
    first = keys.groupBy("d").agg(F.min("i").alias("f"), F.count("*").alias("c")).where("c > 1").select("d", "f")
    again = keys.join(first, "d").where("i is not null and i <> f").select("i", "d", "f").distinct()
    nulls = p.where("i is null").join(first, "d", "left")
    cols = ["i", "d", "u", "p", "f", "m"]
    rows = (
        p.where("i is not null").select("i", "d", "u", "p", F.lit(None).cast("long").alias("f"), F.lit(1).alias("m"))
        .unionByName(nulls.select("i", "d", "u", "p", F.when(F.octet_length("p") >= least, F.col("f")).alias("f"), F.lit(1).alias("m")))
        .unionByName(again.select("i", "d", F.lit(None).cast("string").alias("u"), F.lit(None).cast("binary").alias("p"), "f", F.lit(0).alias("m")))
    )
    # Ranges of (page, digest): many rows without an id, or with one id, still go to many tasks.
    made = rows.select(*cols).repartitionByRange("i", "d").sortWithinPartitions("i", "d", "m", "u").mapInArrow(_writer(folder, roll), _MANIFEST)
    made.write.mode("overwrite").parquet(f"{folder}/_pending")
    pending = spark.read.schema(_MANIFEST).parquet(f"{folder}/_pending")
    done = pending.repartition("name").mapInArrow(_committer(folder), "name string, records long")
    done.write.mode("overwrite").parquet(f"{folder}/_committed")
    pending.drop("temp").write.mode("overwrite").parquet(f"{folder}/_manifest")
    drop_path(spark, f"{folder}/_pending")
    drop_path(spark, f"{folder}/_committed")
    return spark.read.parquet(f"{folder}/_manifest")


def _reader(with_body: bool):
    def run(batches):
        for b in batches:
            for blob in b.column(0):
                rows = []
                for head, body in records(io.BytesIO(blob.as_py())):
                    page, refer = head.get("x-page-id"), head.get("warc-refers-to")
                    rows.append((int(page) if page else None, int(head["x-payload-length"]), head["warc-payload-digest"].removeprefix("sha256:"), head["warc-type"], page_of(refer) if refer else None, head.get("warc-target-uri"), body))
                    if len(rows) == 1000:
                        yield _rows(rows, with_body)
                        rows = []
                yield _rows(rows, with_body)

    return run


def _rows(rows: list, with_body: bool) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * 7
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.binary()]
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "body"]
    n = 7 if with_body else 5
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols[:n], kinds[:n], strict=True)], names=names[:n])


def read_archive(spark: SparkSession, folder: str, with_body: bool = False) -> DataFrame:
    """One row for each record of the shards below folder; files are bounded by the roll size."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").schema("path string, modificationTime timestamp, length long, content binary").load(folder)
    return files.select("content").mapInArrow(_reader(with_body), _PAGES + (", url string, body binary" if with_body else ""))


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write every page, read every record back."""
    folder = fresh_path(spark, "warc")
    write_archive(spark.read.parquet(f"{sf_dir}/pages.parquet"), folder)
    return read_archive(spark, folder)


OP5_SQL = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
k AS (SELECT page_id, strlen(h) AS n, sha256(h) AS d FROM p),
f AS (SELECT d, min(page_id) AS first FROM k WHERE n >= {LEAST} GROUP BY d)
SELECT k.page_id, CAST(n AS BIGINT) AS payload_bytes, k.d AS payload_digest,
  CASE WHEN first IS NOT NULL AND k.page_id IS DISTINCT FROM first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN k.page_id IS DISTINCT FROM first THEN first END AS refers_to
FROM k LEFT JOIN f ON k.d = f.d AND k.n >= {LEAST}"""
