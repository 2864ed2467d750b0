"""WARC archives written in deterministic shards, and read back.

Pages are cut into shards of consecutive ids at quantiles of their bytes, which a
sample by hash gives; digests order the pages of one id, so neither one id nor one
range of ids makes a shard larger than others.  A shard is sorted and written as gzip
members, one a record, and a file is closed when its compressed size passes a limit.
Every file is written under a temporary name and renamed when complete to a name that
ends in its digest: an attempt that is repeated makes the same file and leaves it be.
A manifest, renamed into place last, lists the files that count, so leftovers of lost
tasks are never read.  Headers, record ids and digests depend on the rows alone: the
same table gives the same bytes.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .frames import Workspace, shared_dir

# Fixed values of the archive format.
VERSION = "WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MANIFEST = "_manifest"
_NAMESPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")
#: Bounds of what the driver holds: shards, and sampled rows a shard.
MOST_SHARDS = 1 << 16
_SAMPLED = 32


def _filesystem(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


def _digest(hex_digest: str) -> str:
    return "sha1:" + base64.b32encode(bytes.fromhex(hex_digest)).decode()


def record_id(page_id, hex_digest: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMESPACE, f'{page_id}/{hex_digest}')}>"


def record_bytes(page_id, url: str | None, payload: bytes, digest: str, refers_to, refers_url: str | None, date: str) -> bytes:
    """One uncompressed record; a revisit (``refers_to`` given) leaves its payload out."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    revisit = refers_to is not None
    block = http if revisit else http + payload
    safe = lambda u: quote(u or "about:blank", safe=":/?#[]@!$&'()*+,;=%-._~")
    head = [
        VERSION,
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: {record_id(page_id, digest)}",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {safe(url)}",
        f"WARC-Payload-Digest: {_digest(digest)}",
        f"WARC-Block-Digest: {_digest(hashlib.sha1(block).hexdigest())}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if page_id is not None:
        head.append(f"X-Page-Id: {page_id}")
    if revisit:
        head += [f"WARC-Profile: {REVISIT_PROFILE}", f"WARC-Refers-To: {record_id(refers_to, digest)}", f"WARC-Refers-To-Target-URI: {safe(refers_url)}", f"X-Refers-To-Page-Id: {refers_to}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class _Roller:
    """Writes records of one shard to files below a size, each renamed when complete."""

    def __init__(self, fs: pafs.FileSystem, folder: str, shard: int, roll_bytes: int):
        self.fs, self.folder, self.shard, self.roll = fs, folder, shard, roll_bytes
        self.sequence, self.out, self.done = 0, None, []

    def add(self, record: bytes) -> None:
        member = gzip.compress(record, 6, mtime=0)
        if self.out is None:
            self.temporary = f"{self.folder}/_tmp-{self.shard:06d}-{self.sequence:05d}-{uuid.uuid4().hex}"
            self.out, self.size, self.records, self.sha = self.fs.open_output_stream(self.temporary, compression=None), 0, 0, hashlib.sha1()
        self.out.write(member)
        self.sha.update(member)
        self.size += len(member)
        self.records += 1
        if self.size >= self.roll:
            self.close()

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            name = f"pages-{self.shard:06d}-{self.sequence:05d}-{self.sha.hexdigest()[:16]}.warc.gz"
            publish(self.fs, self.temporary, f"{self.folder}/{name}", self.size)
            self.done.append((name, self.records, self.size, self.sha.hexdigest()))
            self.out, self.sequence = None, self.sequence + 1


def publish(fs: pafs.FileSystem, temporary: str, final: str, size: int) -> None:
    """Renames a complete file; a file of that name and size is the same one from another attempt, and stays."""

    def there() -> bool:
        info = fs.get_file_info(final)
        return info.type == pafs.FileType.File and info.size == size

    if not there():
        try:
            fs.move(temporary, final)
            return
        except OSError:
            if not there():
                raise
    fs.delete_file(temporary)


def _facts(pages: DataFrame, work: Workspace) -> DataFrame:
    """(page_id, url, digest, n) of every row, written once: no payload is in it."""
    body = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    return work.keep(pages.select("page_id", "url", F.sha1(body).alias("digest"), F.length(body).cast("long").alias("n")), "facts")


def _revisits(facts: DataFrame, least: int) -> DataFrame:
    """(page_id, digest, refers_to, refers_url) of the pages that revisit another."""
    large = facts.where((F.col("n") >= least) & F.col("page_id").isNotNull()).select("page_id", "url", "digest")
    groups = (
        large.groupBy("digest")
        .agg(F.max("page_id").alias("refers_to"), F.max_by("url", F.struct("page_id", "url")).alias("refers_url"), F.count(F.lit(1)).alias("n"))
        .where("n > 1")
        .drop("n")
    )
    return large.select("page_id", "digest").distinct().join(groups, "digest").where("page_id <> refers_to")


def _sort_keys(ids: list, digests: list) -> np.ndarray:
    """Keys whose byte order is that of (page_id, digest), null ids first."""
    made = [(b"\0" * 9 if i is None else b"\1" + (i + 2**63).to_bytes(8, "big")) + d.encode() for i, d in zip(ids, digests, strict=True)]
    return np.array(made, dtype="S49") if made else np.zeros(0, "S49")


def shard_bounds(facts: DataFrame, shard_bytes: int) -> np.ndarray:
    """First keys of all shards but the first, from a sample by hash of about 32 rows a shard.

    The sample depends on the rows alone, not on how they are partitioned.  Beyond
    ``MOST_SHARDS`` shards grow instead.
    """
    weight = F.col("n") + 600
    total, rows = facts.agg(F.coalesce(F.sum(weight), F.lit(0)), F.count(F.lit(1))).first()
    shards = min(MOST_SHARDS, -(-int(total) // shard_bytes))
    if shards < 2:
        return _sort_keys([], [])
    level = min(1.0, _SAMPLED * shards / rows)
    hashed = F.pmod(F.xxhash64("page_id", "digest", "url"), F.lit(1 << 30)) < F.lit(int(level * (1 << 30)))
    sample = facts.where(hashed).groupBy("page_id", "digest").agg(F.sum(weight).alias("w")).toArrow()  # 32 * MOST_SHARDS rows expected at most
    keys = _sort_keys(sample.column("page_id").to_pylist(), sample.column("digest").to_pylist())
    order = np.argsort(keys)
    before = np.cumsum(sample.column("w").to_numpy()[order].astype(float))
    if not len(before):
        return _sort_keys([], [])
    cuts = np.searchsorted(before, before[-1] * np.arange(1, shards) / shards)
    return np.unique(keys[order][np.minimum(cuts, len(order) - 1)])


def _shard_of(bounds: np.ndarray) -> Column:
    """The shard of (page_id, digest); only these two columns go to Python workers."""

    @F.pandas_udf("int")
    def shard(ids: pd.Series, digests: pd.Series) -> pd.Series:
        keys = _sort_keys([None if pd.isna(i) else int(i) for i in ids.astype(object)], digests.tolist())
        return pd.Series(np.searchsorted(bounds, keys, side="right").astype(np.int32))

    # as text: pandas would turn ids beside a null into inexact floats
    return shard(F.col("page_id").cast("string"), F.col("digest"))


def write_warc(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", *, revisit_bytes: int = 1000, shard_bytes: int = 1 << 26, roll_bytes: int = 1 << 23, date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """Writes every row as a record and returns the manifest (file, records, bytes, sha1).

    Of rows with equal payloads of at least ``revisit_bytes`` bytes, the one with the
    largest id is the response and the others revisit it.  A null payload is empty; a
    row with a null id is a response that nothing refers to; rows that repeat the
    largest id are all responses.  An empty table writes an empty manifest.  Other
    columns of the table are not read, whatever their names.  ``date`` stands for the
    missing fetch time.  A folder that has a manifest is left alone: FileExistsError.
    Shards hold about ``shard_bytes`` of payload, files ``roll_bytes`` compressed.
    """
    spark = pages.sparkSession
    pages = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(payload_col).cast("string").alias("html"))
    manifest = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/{MANIFEST}")
    store = manifest.getFileSystem(spark._jsc.hadoopConfiguration())
    if store.exists(manifest):
        raise FileExistsError(f"{folder} has a manifest already")
    work = Workspace(spark, "warc-facts")
    facts = _facts(pages, work)
    bounds = shard_bounds(facts, shard_bytes)
    body = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    rows = pages.select("page_id", "url", F.lit(1).alias("kind"), F.sha1(body).alias("digest"), body.alias("payload"))
    notes = _revisits(facts, revisit_bytes).withColumn("kind", F.lit(0))
    # a page's note, if any, sorts right before it: payloads are shuffled once only
    both = rows.unionByName(notes, allowMissingColumns=True).withColumn("shard", _shard_of(bounds))
    placed = both.repartitionById(len(bounds) + 1, F.col("shard")).sortWithinPartitions("shard", "page_id", "digest", "kind", "url")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _filesystem(folder)
        fs.create_dir(base, recursive=True)
        roller, done, noted = None, [], (None, None, None, None)
        for batch in batches:
            col = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
            for k in range(batch.num_rows):
                at = col["shard"][k].as_py()
                if roller is None or roller.shard != at:
                    if roller is not None:
                        roller.close()
                        done += roller.done
                    roller = _Roller(fs, base, at, roll_bytes)
                page, digest = col["page_id"][k].as_py(), col["digest"][k].as_py()
                if not col["kind"][k].as_py():
                    noted = (page, digest, col["refers_to"][k].as_py(), col["refers_url"][k].as_py())
                    continue
                to, to_url = noted[2:] if noted[:2] == (page, digest) else (None, None)
                roller.add(record_bytes(page, col["url"][k].as_py(), col["payload"][k].as_py(), digest, to, to_url, date))
        if roller is not None:
            roller.close()
            done += roller.done
        if done:
            yield pa.RecordBatch.from_arrays([pa.array([d[i] for d in done], t) for i, t in enumerate((pa.string(), pa.int64(), pa.int64(), pa.string()))], names=["file", "records", "bytes", "sha1"])

    temporary = f"{folder}/{MANIFEST}-tmp-{uuid.uuid4().hex}"
    placed.mapInArrow(write, "file string, records long, bytes long, sha1 string").write.parquet(temporary)
    path = spark._jvm.org.apache.hadoop.fs.Path(temporary)
    if store.exists(manifest) or not store.rename(path, manifest):
        raise OSError(f"the manifest of {folder} could not be put in place")
    work.forget("facts")
    return spark.read.parquet(f"{folder}/{MANIFEST}")


def _members(stream) -> Iterator[bytes]:
    """Uncompressed gzip members of a stream, one at a time."""
    waiting = b""
    while True:
        if not waiting:
            waiting = stream.read(1 << 20)
            if not waiting:
                return
        inflate, parts = zlib.decompressobj(31), []
        while not inflate.eof:
            parts.append(inflate.decompress(waiting))
            waiting = inflate.unused_data if inflate.eof else stream.read(1 << 20)
            if not waiting and not inflate.eof:
                raise ValueError("a member is cut short")
        yield b"".join(parts)


def parse_record(raw: bytes) -> dict:
    """Headers of a record, with what its HTTP block says and holds."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if lines[0] != VERSION:
        raise ValueError(f"not a {VERSION} record")
    fields = dict(x.split(": ", 1) for x in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    said = dict(x.split(": ", 1) for x in http.decode().split("\r\n")[1:])
    digest = base64.b32decode(fields["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
    if _digest(hashlib.sha1(block).hexdigest()) != fields["WARC-Block-Digest"]:
        raise ValueError("a block does not match its digest")
    if fields["WARC-Type"] == "response" and hashlib.sha1(payload).hexdigest() != digest:
        raise ValueError("a payload does not match its digest")
    return {"fields": fields, "payload": payload, "payload_bytes": int(said["Content-Length"]), "digest": digest}


def read_warc(spark: SparkSession, folder: str, *, with_payload: bool = False) -> DataFrame:
    """(page_id, url, payload_bytes, payload_digest, record_type, refers_to[, payload]) of the manifest's files.

    Every block and payload is held against its digest.  A revisit has no payload.
    """
    files = spark.read.parquet(f"{folder}/{MANIFEST}").select("file")
    schema = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long" + ", payload binary" * with_payload
    types = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()][: 6 + with_payload]
    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"][: 6 + with_payload]
    number = lambda x: None if x is None else int(x)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _filesystem(folder)
        rows: list[tuple] = []
        held = 0
        pack = lambda: pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], names=names)
        for batch in batches:
            for name in batch.column(0).to_pylist():
                with fs.open_input_stream(f"{base}/{name}", compression=None) as stream:
                    for raw in _members(stream):
                        r = parse_record(raw)
                        f = r["fields"]
                        row = (number(f.get("X-Page-Id")), f["WARC-Target-URI"], r["payload_bytes"], r["digest"], f["WARC-Type"], number(f.get("X-Refers-To-Page-Id")), r["payload"] if f["WARC-Type"] == "response" else None)
                        rows.append(row[: 6 + with_payload])
                        held += len(raw) if with_payload else 200
                        if held > 1 << 22:
                            yield pack()
                            rows, held = [], 0
        if rows:
            yield pack()

    return files.repartition(max(1, spark.sparkContext.defaultParallelism * 4), "file").mapInArrow(read, schema)


def archive_and_read(pages: DataFrame, **settings) -> DataFrame:
    """Writes the pages below the shared folder and returns what the archives hold."""
    folder = shared_dir(pages.sparkSession, "warc")
    write_warc(pages, folder, **settings)
    return read_warc(pages.sparkSession, folder)
