"""Deterministic sharded WARC writing and reading.

Records are range-sorted by page id; a task writes its range to files that are rolled at a compressed size, each under a
temporary name that is renamed when the file is whole, so a lost or repeated task leaves no half file under a final
name; a task repeated after its rename replaces the file by the same bytes.  Headers and digests are made anew from the payload.  The manifest (one row per file) is written last, under a
temporary name too; readers take only files of the manifest, and check lengths and digests.

Of records with equal payloads of at least ``min_revisit`` bytes, the one with the largest page id is the response, and
the others are revisits that refer to it.  Defined cases: null html is an empty payload; null url an empty target; rows
with a null page id sort first; they revisit an equal payload that has an id, and are responses where none has; repeated rows with the largest id are all responses.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundpath.llm.shared import fresh_path, join_keyed, materialise, read_table

MIN_REVISIT = 1000
ROLL_BYTES = 16_000_000
#: One date for all records keeps archives byte-identical between runs.
RECORD_DATE = "2000-01-01T00:00:00Z"
_EOL = b"\r\n"
MANIFEST_SCHEMA = "file string, records bigint, bytes bigint, sha1 string, first_id bigint, last_id bigint"
RECORD_SCHEMA = "page_id bigint, url string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, payload binary"


def _name(page_id) -> str:
    return f"<urn:page:{'null' if page_id is None else page_id}>"


def _page(name: bytes) -> int | None:
    tail = name.rsplit(b":", 1)[1].rstrip(b">")
    return None if tail == b"null" else int(tail)


def make_record(page_id, url: str | None, payload: bytes, digest: str, refers_to, is_revisit: bool) -> bytes:
    """One gzip member with one WARC record."""
    target = "".join(c if c > " " and c != "\x7f" else "%%%02X" % ord(c) for c in url or "")
    lines = [
        b"WARC/1.1",
        b"WARC-Type: " + (b"revisit" if is_revisit else b"response"),
        b"WARC-Record-ID: " + _name(page_id).encode(),
        b"WARC-Date: " + RECORD_DATE.encode(),
        b"WARC-Target-URI: " + target.encode("utf-8", "surrogatepass"),
        b"WARC-Payload-Digest: sha1:" + digest.encode(),
        b"WARC-Payload-Length: " + str(len(payload)).encode(),
    ]
    body = payload
    if is_revisit:
        lines += [b"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", b"WARC-Refers-To: " + _name(refers_to).encode()]
        body = b""
    lines += [b"Content-Type: text/html; charset=utf-8", b"Content-Length: " + str(len(body)).encode(), b"", b""]
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress(_EOL.join(lines) + body + _EOL + _EOL) + packer.flush()


def parse_records(stream):
    """Records of a gzip stream, one by one: (headers, body)."""
    with gzip.GzipFile(fileobj=stream, mode="rb") as f:
        while line := f.readline():
            if line != b"WARC/1.1\r\n":
                raise ValueError(f"not a record's start: {line[:40]!r}")
            headers = {}
            while (line := f.readline()) != _EOL:
                key, _, value = line.rstrip(_EOL).partition(b": ")
                headers[key.decode()] = value
            body = f.read(int(headers["Content-Length"]))
            if f.read(4) != _EOL + _EOL:
                raise ValueError("a record's end is missing")
            yield headers, body


def _writer(folder: str, roll: int):
    def run(batches):
        from pyarrow import fs
        from pyspark import TaskContext

        task = TaskContext.get()
        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base, recursive=True)
        buffer, ids, part = io.BytesIO(), [], 0

        def close():
            nonlocal buffer, ids, part
            name = f"part-{task.partitionId():06d}-{part:05d}.warc.gz"
            data = buffer.getvalue()
            temporary = f"{base}/_tmp-{name}.{task.taskAttemptId()}"
            with store.open_output_stream(temporary, compression=None) as out:
                out.write(data)
            if store.get_file_info(f"{base}/{name}").type != fs.FileType.NotFound:
                store.delete_file(f"{base}/{name}")  # an earlier attempt of this task: some stores refuse to rename onto it
            store.move(temporary, f"{base}/{name}")
            known = [i for i in ids if i is not None]
            row = (name, len(ids), len(data), hashlib.sha1(data).hexdigest(), min(known, default=None), max(known, default=None))
            buffer, ids, part = io.BytesIO(), [], part + 1
            return pa.RecordBatch.from_arrays(
                [pa.array([x], t) for x, t in zip(row, (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64()), strict=True)],
                names=["file", "records", "bytes", "sha1", "first_id", "last_id"],
            )

        for batch in batches:
            for i in range(batch.num_rows):
                page_id, url, payload, digest, answer = (c[i].as_py() for c in batch.columns)
                revisit = answer is not None and answer != page_id
                buffer.write(make_record(page_id, url, payload, digest, answer, revisit))
                ids.append(page_id)
                if buffer.tell() >= roll:
                    yield close()
        if ids:
            yield close()

    return run


def _reader(folder: str, with_payload: bool):
    def run(batches):
        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for name, records in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows, held, n = [], 0, 0
                with store.open_input_stream(f"{base}/{name}", compression=None) as raw:
                    for head, body in parse_records(raw):
                        kind, size = head["WARC-Type"].decode(), int(head["WARC-Payload-Length"])
                        digest = head["WARC-Payload-Digest"].decode().removeprefix("sha1:")
                        if kind == "response" and (len(body) != size or hashlib.sha1(body).hexdigest() != digest):
                            raise ValueError(f"{name}: payload of {head['WARC-Record-ID']!r} is damaged")
                        refers = _page(head["WARC-Refers-To"]) if kind == "revisit" else None
                        url = head["WARC-Target-URI"].decode("utf-8", "replace")
                        rows.append((_page(head["WARC-Record-ID"]), url, size, digest, kind, refers, body if with_payload and kind == "response" else None))
                        held, n = held + len(body), n + 1
                        if len(rows) >= 2000 or held > 8_000_000:
                            yield _rows(rows)
                            rows, held = [], 0
                if n != records:
                    raise ValueError(f"{name}: {n} records, the manifest has {records}")
                if rows:
                    yield _rows(rows)

    return run


def _rows(rows):
    types = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary())
    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)


def write_warc(pages: DataFrame, folder: str, partitions: int | None = None, roll_bytes: int = ROLL_BYTES, min_revisit: int = MIN_REVISIT) -> DataFrame:
    """Write ``pages`` (page_id, url, html) below ``folder`` (any URI that pyarrow's file systems reach) and return the
    manifest, which lies in ``folder``/manifest."""
    spark = pages.sparkSession
    payload = F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload"), F.sha1(payload).alias("digest"))
    big = rows.filter(F.octet_length("payload") >= min_revisit)
    answers = big.groupBy("digest").agg(F.max("page_id").alias("answer"), F.count("*").alias("rows_of")).filter("rows_of > 1 and answer is not null")
    met = join_keyed(big, materialise(answers, "answers"), "digest", "rows_of", pages.count(), "left")
    short = rows.filter(F.octet_length("payload") < min_revisit).withColumn("answer", F.lit(None).cast("bigint"))
    rows = met.unionByName(short).select("page_id", "url", "payload", "digest", "answer")
    n = partitions or max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    ordered = rows.repartitionByRange(n, "page_id").sortWithinPartitions("page_id", "url", "digest")
    manifest = ordered.mapInArrow(_writer(folder, roll_bytes), MANIFEST_SCHEMA)
    draft = f"{folder}/_manifest"
    manifest.write.parquet(draft)
    jvm = spark.sparkContext._jvm
    old, new = jvm.org.apache.hadoop.fs.Path(draft), jvm.org.apache.hadoop.fs.Path(f"{folder}/manifest")
    if not old.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).rename(old, new):
        raise OSError(f"{folder}: the manifest could not be committed")
    return read_manifest(spark, folder)


def read_manifest(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.schema(MANIFEST_SCHEMA).parquet(f"{folder}/manifest")


def read_warc(spark: SparkSession, folder: str, with_payload: bool = False) -> DataFrame:
    """The records of the files in the manifest; responses with their payload if asked for."""
    files = read_manifest(spark, folder).select("file", "records")
    n = max(1, files.count())
    return files.repartition(n, "file").mapInArrow(_reader(folder, with_payload), RECORD_SCHEMA)


def op10_warc(spark, sf_dir: str) -> DataFrame:
    folder = fresh_path(spark, "warc")
    if "://" not in folder and folder.startswith("/"):
        folder = "file://" + folder
    write_warc(read_table(spark, sf_dir, "pages"), folder)
    return read_warc(spark, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


QUERIES = {"op10_warc": op10_warc}
ORACLES = {
    "op10_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
 d AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS n, sha1(h) AS s FROM p),
 a AS (SELECT *, CASE WHEN n >= 1000 THEN max(page_id) OVER (PARTITION BY s) ELSE page_id END AS top FROM d)
SELECT page_id, n AS payload_bytes, s AS payload_digest, CASE WHEN top IS DISTINCT FROM page_id THEN 'revisit' ELSE 'response' END AS record_type,
 CASE WHEN top IS DISTINCT FROM page_id THEN top END AS refers_to FROM a"""
}
