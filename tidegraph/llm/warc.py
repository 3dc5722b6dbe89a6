"""Deterministic sharded WARC writer and its reader.

Records are dealt into key ranges whose number and bounds come from the input alone (its bytes, and the ids with the
least hashes as the sample), one range to a task, sorted within them, and written as gzip members. A file is rolled when its
compressed bytes reach `roll_bytes`. Headers, record ids, block and payload digests are made anew. A
task writes under a temporary name of its own attempt, renames the finished file, and reports it;
the reported rows become the manifest, itself written through Spark's committer and sealed last by a
marker. A retried task writes the same bytes to the same final names; files that no manifest row
names are not part of the archive.

Records with equal payloads (same SHA-256 and length) of at least `revisit_from` bytes are written once, as the response with
the least id; the others are revisit records that refer to it.

Cases: null html is an empty payload; null url is written as an empty target. A null id is sorted first and
named "null" (it revisits the least id that is not null, and is a response where all are null); repeated ids are separate records (a
repeated row with the least id is a response once more). Empty tables give an archive with an empty manifest. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import math
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions.session import scratch_path, stored
from tidegraph.llm.blocks import range_of

MANIFEST = "shard long, part int, path string, records long, bytes long, sha256 string"
SAMPLE = 64  # ids sampled for each shard, fewer beyond 16,384 shards
MOST_SAMPLE = 1 << 20
MOST_SHARDS = 65536  # bounds that a plan holds; 64 MB each up to 4 TB, beyond it a task streams more (1.5 GB at 100 TB), in files of roll_bytes as ever
DATE = "2024-01-01T00:00:00Z"


def _fs(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(key: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, 'page:' + key)}>"


def record(kind: str, page: str, url: str, payload: bytes, digest: str, refers: str | None) -> bytes:
    body = payload if kind == "response" else b""
    head = [f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page)}", f"WARC-Date: {DATE}", f"WARC-Target-URI: {''.join(url.split())}", f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Block-Digest: sha1:{base32_sha1(body)}", f"X-Page-ID: {page}", f"X-Payload-Length: {len(payload)}"]
    if refers is not None:
        head += [f"WARC-Refers-To: {record_id(refers)}", f"X-Refers-To-Page-ID: {refers}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}"]
    return "WARC/1.1\r\n".encode() + "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def _gz(data: bytes) -> bytes:
    c = zlib.compressobj(6, zlib.DEFLATED, 31)
    return c.compress(data) + c.flush()


def _rows_of(batches, step: int = 256):
    for batch in batches:
        for at in range(0, batch.num_rows, step):
            yield from batch.slice(at, step).to_pylist()


def _writer(folder: str, roll_bytes: int):
    def run(batches):
        rows: dict[str, list] = {k: [] for k in ("shard", "part", "path", "records", "bytes", "sha256")}
        store, base = _fs(folder)
        open_ = None

        def close():
            nonlocal open_
            if open_ is None:
                return
            shard, part, temp, sink, n, size, sha = open_
            sink.close()
            final = f"{base}/shard-{shard:06d}-{part:05d}.warc.gz"
            store.move(temp, final)
            for k, v in zip(rows, (shard, part, f"{folder}/shard-{shard:06d}-{part:05d}.warc.gz", n, size, sha.hexdigest()), strict=True):
                rows[k].append(v)
            open_ = None

        tagged, known = None, {}  # the tags of one id come before its records
        for row in _rows_of(batches):
            if row["_kind"] == 0:
                if row["_id"] != tagged:
                    tagged, known = row["_id"], {}
                known[row["_same"]] = row["_to"]
                continue
            if open_ is None:
                part = 0
            elif open_[5] >= roll_bytes:
                part = open_[1] + 1
                close()
            if open_ is None:
                temp = f"{base}/.tmp-{row['_shard']:06d}-{part:05d}-{uuid.uuid4().hex}"
                open_ = [row["_shard"], part, temp, store.open_output_stream(temp), 0, 0, hashlib.sha256()]
            payload = (row["_html"] or "").encode()
            page = "null" if row["_id"] is None else str(row["_id"])
            refers = known.get(hashlib.sha256(payload).digest()) if known and row["_id"] == tagged else None
            refers = None if refers is None else str(refers)
            data = _gz(record("response" if refers is None else "revisit", page, row["_url"] or "", payload, base32_sha1(payload), refers))
            open_[3].write(data)
            open_[6].update(data)
            open_[4] += 1
            open_[5] += len(data)
        close()
        yield pa.RecordBatch.from_arrays([pa.array(rows["shard"], pa.int64()), pa.array(rows["part"], pa.int32()), pa.array(rows["path"], pa.string()), pa.array(rows["records"], pa.int64()), pa.array(rows["bytes"], pa.int64()), pa.array(rows["sha256"], pa.string())], names=[*rows])

    return run


def write_archive(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", revisit_from: int = 0, shard_bytes: int = 64_000_000, roll_bytes: int = 16_000_000) -> DataFrame:
    """Writes the archive under folder (on storage all executors share) and returns its manifest."""
    store, base = _fs(folder)
    store.create_dir(base, recursive=True)
    rows = pages.select(F.col(id_col).cast("long").alias("_id"), F.col(url_col).alias("_url"), F.col(payload_col).alias("_html"))
    payload = F.coalesce(F.col("_html"), F.lit("")).cast("binary")
    keyed = stored(rows.select("_id", F.unhex(F.sha2(payload, 256)).alias("_same"), F.octet_length(payload).cast("long").alias("_n")), "warc-keys")
    total = keyed.agg(F.sum("_n")).first()[0] or 0
    shards = int(min(MOST_SHARDS, max(1, -(-total // shard_bytes))))
    sample = sorted(r["_id"] for r in keyed.where("_id is not null").select("_id", F.xxhash64("_id").alias("h")).orderBy("h", "_id").limit(min(SAMPLE * shards, MOST_SAMPLE)).collect()) if shards > 1 else []
    bounds = sorted({sample[len(sample) * i // shards] for i in range(1, shards)}) if sample else []
    # only the keys of repeated payloads are joined; the payloads themselves are shuffled once, together with these tags
    copies = keyed.where(F.col("_n") >= revisit_from).groupBy("_same", "_n").agg(F.min("_id").alias("_to"), F.count("*").alias("c")).where("c > 1").drop("c")
    tags = keyed.join(copies, ["_same", "_n"]).where("not _id <=> _to").select("_id", "_same", "_to").distinct()
    shard = F.when(F.col("_id").isNull(), 0).otherwise(range_of(F.col("_id"), bounds)).cast("int")
    ready = tags.select(F.lit(0).alias("_kind"), "_id", F.lit(None).cast("string").alias("_url"), F.lit(None).cast("string").alias("_html"), "_same", "_to")
    ready = ready.unionByName(rows.select(F.lit(1).alias("_kind"), "*"), allowMissingColumns=True).withColumn("_shard", shard)
    ready = ready.repartitionById(shards, F.col("_shard")).sortWithinPartitions("_id", "_kind", "_url", "_html")
    manifest = ready.mapInArrow(_writer(folder, roll_bytes), MANIFEST)
    manifest.write.mode("overwrite").parquet(f"{folder}/_manifest")
    with store.open_output_stream(f"{base}/_COMMITTED") as seal:
        seal.write(b"ok\n")
    return pages.sparkSession.read.schema(MANIFEST).parquet(f"{folder}/_manifest")


RECORDS = "page_id string, target_uri string, payload_bytes long, payload_digest string, record_type string, refers_to string, verified boolean, payload string"


def _records(stream):
    """Header fields and block of each record of an uncompressed WARC stream."""
    while True:
        line = stream.readline()
        if not line:
            return
        if line.strip() != b"WARC/1.1":
            raise ValueError(f"not a WARC record: {line[:40]!r}")
        fields = {}
        while (line := stream.readline().rstrip(b"\r\n")):
            k, _, v = line.decode().partition(": ")
            fields[k] = v
        body = stream.read(int(fields["Content-Length"]))
        stream.read(4)
        yield fields, body


def read_archive(spark: SparkSession, folder: str, payloads: bool = False) -> DataFrame:
    """One row a record of a committed archive; verified: the block's digest and, of responses, the payload's hold."""
    store, base = _fs(folder)
    store.get_file_info(base)
    with store.open_input_stream(f"{base}/_COMMITTED") as seal:
        seal.read()
    manifest = spark.read.schema(MANIFEST).parquet(f"{folder}/_manifest")
    names = [x.split()[0] for x in RECORDS.split(", ")]

    def run(batches):
        for batch in batches:
            for path in batch.column("path").to_pylist():
                own, at = _fs(path)
                with own.open_input_stream(at, compression=None) as raw:
                    out: list[list] = [[] for _ in names]
                    with gzip.GzipFile(fileobj=raw) as stream:
                        for f, body in _records(stream):
                            response = f["WARC-Type"] == "response"
                            digest = f["WARC-Payload-Digest"].removeprefix("sha1:")
                            ok = f["WARC-Block-Digest"] == f"sha1:{base32_sha1(body)}" and (not response or base32_sha1(body) == digest)
                            for k, v in enumerate((f["X-Page-ID"], f["WARC-Target-URI"], int(f["X-Payload-Length"]), digest, f["WARC-Type"], f.get("X-Refers-To-Page-ID"), ok, body.decode() if payloads and response else None)):
                                out[k].append(v)
                            if len(out[0]) >= 500:
                                yield _batch(out)
                                out = [[] for _ in names]
                    yield _batch(out)

    def _batch(out):
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, (pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.bool_(), pa.string()), strict=True)], names=names)

    files = manifest.select("path")
    n = files.count()  # about eight files to a task, but no fewer tasks than there are cores for
    return files.repartition(max(1, min(n, spark.sparkContext.defaultParallelism * 2), -(-n // 8))).mapInArrow(run, RECORDS)


def archived(pages: DataFrame, folder: str | None = None, **options) -> DataFrame:
    """Writes pages and reads the archive back: page_id, payload_bytes, payload_digest, record_type, refers_to, verified."""
    spark = pages.sparkSession
    folder = folder or scratch_path(spark, "warc")
    write_archive(pages, folder, **options)
    back = read_archive(spark, folder)
    as_id = lambda c: F.when(F.col(c) != "null", F.col(c).cast("long"))
    return back.select(as_id("page_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", as_id("refers_to").alias("refers_to"), "verified")
