"""Deterministic sharded WARC writer and reader.

Records are dealt to shards by exact ranks of their keys, so that shards depend on the rows alone, sorted, and written as one
gzip member each into files that roll at a compressed size, under temporary names; each task reports its files as manifest
rows, and only files in the manifest are moved to their final names. A task that is run again leaves files that no manifest
names, so a lost executor cannot duplicate or lose records. Headers and digests are made from the payload alone: a rerun
writes the same bytes. Each content has a folder of its own, named by the digests of its files; the manifest that names
it is put in place last, so a folder that is written again never mixes old and new records.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, drop_cut, parts, scratch

PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2000-01-01T00:00:00Z"
MANIFEST = "part int, seq int, temporary string, name string, records long, bytes long, sha256 string"


def _fs(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


def revisits(pages: DataFrame, least: int = 100, key: str = "page_id", payload: str = "html") -> DataFrame:
    """(key, digest, refers_to, refers_uri) of the records whose payload of at least ``least`` bytes a smaller key has too.
    Only digests move between executors; equal digests are reduced before the shuffle and joined over salted keys."""
    body = F.coalesce(F.col(payload), F.lit("")).cast("binary")
    slim = pages.select(F.col(key).alias("id"), F.col("url"), F.sha2(body, 256).alias("digest"), F.octet_length(body).alias("n")).filter(F.col("n") >= least)
    first = slim.groupBy("digest").agg(F.min(F.struct("id", "url")).alias("first"), F.max("id").alias("last")).filter("last > first.id")
    salts = 32
    first = first.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return slim.select("id", "digest", F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int").alias("salt")).join(first, ["digest", "salt"]).filter("id > first.id").select("id", "digest", F.col("first.id").alias("refers_to"), F.col("first.url").alias("refers_uri")).distinct()


def _record(page_id: int, url: str | None, payload: bytes, digest: str, refers_to: int | None, refers_uri: str | None) -> bytes:
    clean = lambda u: "".join(c for c in (u or "about:blank") if c > " ")  # noqa: E731  a header is one line
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http + (payload if refers_to is None else b"")
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page:{page_id}:{digest}')}>",
        f"WARC-Target-URI: {clean(url)}",
        f"WARC-Date: {DATE}",
        "Content-Type: application/http;msgtype=response",
        f"WARC-Block-Digest: sha256:{hashlib.sha256(block).hexdigest()}",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"X-Page-Id: {page_id}",
    ]
    if refers_to is not None:
        head += [f"WARC-Profile: {PROFILE}", "WARC-Truncated: length", f"WARC-Refers-To-Target-URI: {clean(refers_uri)}", f"WARC-Refers-To-Date: {DATE}", f"X-Refers-To-Page-Id: {refers_to}"]
    head.append(f"Content-Length: {len(block)}")
    return ("\r\n".join(head) + "\r\n\r\n").encode() + block + b"\r\n\r\n"


def shard_count(total: int) -> int:
    """About 256 shards, of 8 MB at least and 512 MB at most: fixed by the bytes of the payloads."""
    return max(1, -(-total // max(8 << 20, min(512 << 20, total // 256))))


def shard_starts(pages: DataFrame, shards: int, rows: int, key: str) -> list[int]:
    """The first key of each shard but the first, by exact rank: key number i * rows / shards in sorted order. Keys are sorted
    in ranges and numbered there; only one number per range and one key per shard reach the driver."""
    if shards < 2:
        return []
    each = -(-rows // shards)
    spark = pages.sparkSession

    def number(batches):
        from pyspark import TaskContext

        part, at = TaskContext.get().partitionId(), 0
        for b in batches:
            n = b.num_rows
            yield pa.RecordBatch.from_arrays([pa.array([part] * n, pa.int32()), pa.array(range(at, at + n), pa.int64()), b.column(0)], ["part", "at", "id"])
            at += n

    ids = pages.select(F.col(key).alias("id")).repartitionByRange(parts(spark), "id").sortWithinPartitions("id")
    placed = cut(ids.mapInArrow(number, "part int, at long, id long"), "warc-ranks")
    sizes = {r["part"]: r["n"] for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect()}
    base, before = 0, []
    for p in sorted(sizes):
        before.append((p, base))
        base += sizes[p]
    bases = F.broadcast(spark.createDataFrame(before, "part int, base long"))
    got = placed.join(bases, "part").filter(((F.col("base") + F.col("at")) % each == 0) & (F.col("base") + F.col("at") > 0)).select("id").collect()
    drop_cut(placed)
    return sorted({r["id"] for r in got})


def write(pages: DataFrame, at: str | None = None, roll_bytes: int = 256 << 20, level: int = 4, least: int = 100, key: str = "page_id", payload: str = "html", shards: int | None = None, keep_old: bool = False) -> DataFrame:
    """Write one record per row of ``pages`` (key long, url string, payload string) under the folder ``at`` and return the
    manifest: path, records, bytes and sha256 of each file, in key order. ``current`` finds it again.

    A null payload is an empty one, a null url is about:blank, a row with a null key is left out (a record needs an id).
    Rows that repeat a key are records of their own; of equal payloads those with the smallest key are responses. Other
    columns are ignored. An empty table gives an empty manifest. Written to a folder again, the new archives take the place of the
    old ones, which are deleted unless ``keep_old``; equal rows give the same files, byte by byte.
    """
    spark = pages.sparkSession
    at = at or scratch(spark, "warc")
    pages = pages.filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col("url").cast("string").alias("url"), F.col(payload).alias("body"))
    size = pages.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("body")), F.lit(0)).alias("bytes")).first()
    shards = shards or shard_count(size["bytes"] + 512 * size["n"])
    starts = shard_starts(pages, shards, size["n"], "id")
    again = revisits(pages, least, "id", "body")
    none = F.lit(None)
    rows = pages.select("id", F.lit(1).alias("kind"), "url", "body", none.cast("long").alias("refers_to"), none.cast("string").alias("refers_uri")).unionByName(
        again.select("id", F.lit(0).alias("kind"), none.cast("string").alias("url"), F.col("digest").alias("body"), "refers_to", "refers_uri")
    )

    @F.pandas_udf("int")
    def shard_of(ids: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(np.array(starts, np.int64), ids.to_numpy(), side="right").astype(np.int32))

    # a note that a page is a revisit sorts just before the page, so that payloads move once
    shard = shard_of("id") if starts else F.lit(0)
    rows = rows.withColumn("shard", shard).repartitionById(len(starts) + 1, "shard").sortWithinPartitions("id", "kind", "refers_to", F.sha2(F.coalesce("body", F.lit("")), 256), "url")
    temporary = f"_temporary-{uuid.uuid4().hex}"

    def run(batches):
        from pyspark import TaskContext

        fs, root = _fs(at)
        fs.create_dir(f"{root}/{temporary}", recursive=True)
        attempt = TaskContext.get().taskAttemptId()
        out, made, seq, notes = None, [], 0, (None, {})

        def close():
            nonlocal out
            if out:
                out["f"].close()
                made.append((out["part"], out["seq"], out["tmp"], f"records-{out['part']:06d}-{out['seq']:06d}.warc.gz", out["records"], out["bytes"], out["sha"].hexdigest()))
                out = None

        for b in batches:
            for x in range(b.num_rows):
                pid, kind, url, body, to, uri, part = (b.column(c)[x].as_py() for c in range(7))
                if notes[0] != pid:
                    notes = (pid, {})
                if kind == 0:
                    notes[1][body] = (to, uri)
                    continue
                body = (body or "").encode("utf-8", "surrogatepass")
                digest = hashlib.sha256(body).hexdigest()
                refers = notes[1].get(digest, (None, None))
                pack = zlib.compressobj(level, zlib.DEFLATED, 31)
                data = pack.compress(_record(pid, url, body, digest, *refers)) + pack.flush()
                if out and out["bytes"] + len(data) > roll_bytes:
                    close()
                if out is None:
                    tmp = f"{root}/{temporary}/{part}-{attempt}-{seq}"
                    out = {"f": fs.open_output_stream(tmp, compression=None), "tmp": tmp, "part": part, "seq": seq, "records": 0, "bytes": 0, "sha": hashlib.sha256()}
                    seq += 1
                out["f"].write(data)
                out["sha"].update(data)
                out["records"] += 1
                out["bytes"] += len(data)
        close()
        if made:
            yield pa.RecordBatch.from_pylist([dict(zip(("part", "seq", "temporary", "name", "records", "bytes", "sha256"), m)) for m in made], pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("temporary", pa.string()), ("name", pa.string()), ("records", pa.int64()), ("bytes", pa.int64()), ("sha256", pa.string())]))

    manifest = cut(rows.mapInArrow(run, MANIFEST), "warc-manifest")
    # the folder is named by what is in it
    seen = manifest.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("name", "sha256")).alias("x"), F.sum(F.xxhash64("sha256", "name").cast("decimal(38,0)")).alias("s")).first()
    folder = "archives-" + hashlib.sha256(f"{seen['n']} {seen['x']} {seen['s']}".encode()).hexdigest()[:24]

    def commit(batches):
        from pyarrow.fs import FileType

        fs, root = _fs(at)
        fs.create_dir(f"{root}/{folder}", recursive=True)
        for b in batches:
            for m in b.to_pylist():
                name = f"{root}/{folder}/{m['name']}"
                # an equal file may be there, from a write of the same rows or an earlier attempt of this task
                if fs.get_file_info(m["temporary"]).type != FileType.NotFound:
                    if fs.get_file_info(name).type != FileType.NotFound:
                        fs.delete_file(name)
                    fs.move(m["temporary"], name)
            yield b.select(["part", "seq", "name", "records", "bytes", "sha256"])

    done = cut(manifest.mapInArrow(commit, "part int, seq int, name string, records long, bytes long, sha256 string"), "warc-committed")
    told = done.select("part", "seq", F.concat(F.lit(f"{folder}/"), "name").alias("name"), "records", "bytes", "sha256")
    told.coalesce(1).sortWithinPartitions("part", "seq").write.mode("overwrite").json(f"{at}/{temporary}/manifest")
    drop_cut(manifest)
    jvm = spark._jvm
    root = jvm.org.apache.hadoop.fs.Path(at)
    fs = root.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    path = lambda x: jvm.org.apache.hadoop.fs.Path(root, x)
    fs.delete(path("_manifest"), True)
    if not fs.rename(path(f"{temporary}/manifest"), path("_manifest")):
        raise OSError(f"the manifest could not be put in place in {at}")
    for f in fs.listStatus(root):
        name = f.getPath().getName()
        if name == temporary or (name.startswith("archives-") and name != folder and not keep_old):
            fs.delete(f.getPath(), True)
    return done.select("part", "seq", F.concat(F.lit(f"{at}/{folder}/"), "name").alias("path"), "records", "bytes", "sha256")


def current(spark: SparkSession, at: str) -> DataFrame:
    """The manifest of the archives that a folder holds now."""
    got = spark.read.schema("part int, seq int, name string, records long, bytes long, sha256 string").json(f"{at}/_manifest")
    return got.select("part", "seq", F.concat(F.lit(f"{at}/"), "name").alias("path"), "records", "bytes", "sha256")


class _Digested:
    """A stream that knows the digest of what was read."""

    def __init__(self, stream):
        self.stream, self.sha = stream, hashlib.sha256()

    def read(self, n: int) -> bytes:
        data = self.stream.read(n)
        self.sha.update(data)
        return data


def records(stream):
    """(headers, block) of each record of a gzipped archive, read a piece at a time."""
    buf, more, d = bytearray(), True, None
    raw = b""
    while more or raw:
        if not raw:
            raw = stream.read(1 << 20)
            more = bool(raw)
            if not raw:
                break
        d = d or zlib.decompressobj(31)
        buf += d.decompress(raw)
        raw = d.unused_data
        if not d.eof:
            continue
        d = None
        end = buf.index(b"\r\n\r\n")
        lines = bytes(buf[:end]).decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError("not a WARC record")
        head = dict(x.split(": ", 1) for x in lines[1:])
        n = int(head["Content-Length"])
        block = bytes(buf[end + 4 : end + 4 + n])
        if len(block) != n or hashlib.sha256(block).hexdigest() != head["WARC-Block-Digest"].removeprefix("sha256:"):
            raise ValueError(f"damaged record {head.get('WARC-Record-ID')}")
        yield head, block
        buf = bytearray()
    if d is not None or buf:
        raise ValueError("the archive ends inside a record")


def read(manifest: DataFrame, body: bool = True) -> DataFrame:
    """Read the archives of a manifest: one row per record with its headers' values, verified digests and the payload
    (null for revisits, or where ``body`` is false). Damaged or cut archives, and files that are not those of the manifest, raise
    an error."""
    schema = "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"
    arrow = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])

    def run(batches):
        for b in batches:
            for path, digest_of_file in zip(*(c.to_pylist() for c in b.columns)):
                fs, at = _fs(path)
                rows, size = [], 0
                with fs.open_input_stream(at, compression=None) as f:
                    f = _Digested(f)
                    for head, block in records(f):
                        cut_at = block.index(b"\r\n\r\n") + 4
                        http = dict(x.split(": ", 1) for x in block[:cut_at].decode().strip().split("\r\n")[1:])
                        kind, data, digest = head["WARC-Type"], block[cut_at:], head["WARC-Payload-Digest"].removeprefix("sha256:")
                        if kind == "response" and hashlib.sha256(data).hexdigest() != digest:
                            raise ValueError(f"damaged payload {head['WARC-Record-ID']}")
                        to = head.get("X-Refers-To-Page-Id")
                        rows.append((int(head["X-Page-Id"]), head["WARC-Target-URI"], kind, int(http["Content-Length"]), digest, int(to) if to else None, data if body and kind == "response" else None))
                        size += len(block)
                        if size > 4 << 20:
                            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow.types)], schema=arrow)
                            rows, size = [], 0
                if f.sha.hexdigest() != digest_of_file:
                    raise ValueError(f"{path} is not the file of the manifest")
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow.types)], schema=arrow)

    return manifest.select("path", "sha256").repartition(parts(manifest.sparkSession)).mapInArrow(run, schema)
