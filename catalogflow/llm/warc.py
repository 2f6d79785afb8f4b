"""Operator 1: deterministic sharded WARC files.

Records are range-sorted by URL (host labels reversed) and id. Ranges hold equal bytes of html by the running total over all
keys in order, so their borders depend on the rows alone, not on how these are stored or scheduled. Every record gets fresh headers, digests and an
id derived from its content, and is a gzip member of its own. Inside a range, files roll when their compressed size reaches
``file_bytes``. Tasks write under names of their own in ``_temporary``; the rows of the attempts that succeeded, and no others, become
the manifest, by which files are then moved to their final names; a second run of that step changes nothing. ``_SUCCESS``
is written last. Equal input gives equal bytes.

Defined cases: null or empty html is a record with an empty body; null url is written as ``urn:no-url``; null ids sort
first; ties and repeated rows are all written, in order of id and digest; an empty table gives no file but an empty manifest.
Records are whole, however long. Extra columns aren't read.
"""

from __future__ import annotations

import base64
import bisect
import gzip
import hashlib
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from catalogflow.llm import text as tx
from catalogflow.llm.hosts import host_of
from catalogflow.llm.order import running_total
from catalogflow.session import fresh_path, staged

INDEX = "page_id bigint, shard int, temp string, name string, offset bigint, length bigint, raw_bytes bigint, digest string"


def sort_key() -> Column:
    """Host labels from right to left, then the rest of the URL, then the id."""
    rest = F.regexp_replace(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.\-]*://[^/?#]*", "")
    return F.concat(F.array_join(F.reverse(F.split(host_of("url"), "[.]")), ","), F.lit(")"), rest, F.lit(" "), F.lpad(F.coalesce(F.col("page_id").cast("string"), F.lit("")), 20, "0"))


def sha1(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def member(kind: str, uri: str | None, content_type: str, block: bytes, payload_digest: str | None, date: str) -> bytes:
    """One record as a gzip member."""
    digest = sha1(block)
    name = uuid.uuid5(uuid.NAMESPACE_URL, f"{kind} {uri} {digest}")
    head = [f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{name}>", f"WARC-Date: {date}"]
    head += [f"WARC-Target-URI: {uri}"] if kind == "response" else [f"WARC-Filename: {uri}"]
    head += [f"WARC-Payload-Digest: {payload_digest}"] if payload_digest else []
    head += [f"WARC-Block-Digest: {digest}", f"Content-Type: {content_type}", f"Content-Length: {len(block)}"]
    return gzip.compress(("WARC/1.1\r\n" + "\r\n".join(head) + "\r\n\r\n").encode() + block + b"\r\n\r\n", 6, mtime=0)


def response(uri: str | None, html: str | None, date: str) -> tuple[bytes, str, int]:
    body = (html or "").encode("utf-8", "surrogatepass")
    uri = "urn:no-url" if uri is None else uri.replace("\r", "%0D").replace("\n", "%0A")
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    digest = sha1(body)
    return member("response", uri, "application/http; msgtype=response", http + body, digest, date), digest, len(body)


def borders(keyed: DataFrame, total: int, shard_bytes: int) -> list[str]:
    """Least keys of all ranges but the first, so that each range has as near ``shard_bytes`` of html as whole keys allow; keyed: (key, size).

    All keys count, not a sample. Only the borders come to the driver: one for each ``shard_bytes``.
    """
    if total <= shard_bytes:
        return []
    shards = -(-total // shard_bytes)
    cut = running_total(keyed, ["key"], "size").groupBy(F.expr(f"cast((cast(before as decimal(38,0)) * {shards}) div {total} as bigint)").alias("shard")).agg(F.min("key").alias("key"))
    return sorted(set(cut.where("shard > 0").toPandas()["key"]))


def write_warc(pages: DataFrame, path: str, shard_bytes: int = 256_000_000, file_bytes: int = 64_000_000, date: str = "2000-01-01T00:00:00Z") -> DataFrame:
    """Write ``pages`` (page_id, url, html); returns the index (page_id, shard, file, offset, length, raw_bytes, digest).

    shard_bytes: html per range, which is one task's work; file_bytes: compressed size at which a file is closed.
    """
    from pyarrow import fs

    spark = pages.sparkSession
    keyed = pages.select("page_id", "url", "html", sort_key().alias("key"))
    size = keyed.agg(F.sum(F.octet_length("html"))).first()[0] or 0
    edge = spark.sparkContext.broadcast(borders(keyed.select("key", F.coalesce(F.octet_length("html"), F.lit(0)).cast("bigint").alias("size")), size, shard_bytes))
    temporary = f"{path}/_temporary"

    def build(batches):
        tx.low_memory()
        for part in tx.slices(batches, "html", 2_000_000):
            made = [response(u, h, date) for u, h in zip(part.column("url").to_pylist(), part.column("html").to_pylist())]
            shard = [bisect.bisect_right(edge.value, k) for k in part.column("key").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [pa.array(shard, pa.int32()), part.column("key"), part.column("page_id"), pa.array([m[1] for m in made]), pa.array([m[2] for m in made], pa.int64()), pa.array([m[0] for m in made], pa.binary())],
                ["shard", "key", "page_id", "digest", "raw_bytes", "member"],
            )

    def store(batches):
        tx.low_memory()
        system, root = fs.FileSystem.from_uri(temporary)
        system.create_dir(root, recursive=True)
        out, at, now, number, temp, name = None, 0, None, 0, "", ""
        try:
            for batch in batches:
                rows: dict[str, list] = {k: [] for k in ("temp", "name", "offset", "length")}
                for shard, data in zip(batch.column("shard").to_pylist(), batch.column("member")):
                    if out is None or shard != now or at >= file_bytes:
                        number = 0 if shard != now else number + 1
                        if out is not None:
                            out.close()
                        now, name, temp = shard, f"part-{shard:06d}-{number:05d}.warc.gz", uuid.uuid4().hex
                        out, at = system.open_output_stream(f"{root}/{temp}"), 0
                        first = member("warcinfo", name, "application/warc-fields", b"software: catalogflow\r\nformat: WARC File Format 1.1\r\n", None, date)
                        out.write(first)
                        at += len(first)
                    buffer = data.as_buffer()
                    out.write(buffer)
                    for k, v in zip(rows, (temp, name, at, buffer.size)):
                        rows[k].append(v)
                    at += buffer.size
                yield pa.RecordBatch.from_arrays(
                    [batch.column("page_id"), batch.column("shard"), pa.array(rows["temp"], pa.string()), pa.array(rows["name"], pa.string()), pa.array(rows["offset"], pa.int64()), pa.array(rows["length"], pa.int64()), batch.column("raw_bytes"), batch.column("digest")],
                    [x.split()[0] for x in INDEX.split(", ")],
                )
        finally:
            if out is not None:
                out.close()

    records = keyed.mapInArrow(build, "shard int, key string, page_id bigint, digest string, raw_bytes bigint, member binary")
    # one partition for each range: hashing would put several ranges into one
    written = records.repartitionById(len(edge.value) + 1, "shard").sortWithinPartitions("shard", "key", "page_id", "digest").mapInArrow(store, INDEX)
    manifest = staged(written, "warc-manifest")
    commit(manifest, path)
    return manifest.select("page_id", "shard", F.col("name").alias("file"), "offset", "length", "raw_bytes", "digest")


def commit(manifest: DataFrame, path: str) -> None:
    """Move the files that the manifest names to their final names; files already moved are left."""
    from pyarrow import fs

    def move(batches):
        system, root = fs.FileSystem.from_uri(path)
        for batch in batches:
            for temp, name in zip(batch.column("temp").to_pylist(), batch.column("name").to_pylist()):
                if system.get_file_info(f"{root}/_temporary/{temp}").type != fs.FileType.NotFound:
                    system.move(f"{root}/_temporary/{temp}", f"{root}/{name}")
                elif system.get_file_info(f"{root}/{name}").type == fs.FileType.NotFound:
                    raise FileNotFoundError(name)
            yield batch

    files = manifest.groupBy("temp", "name").agg(F.count("*").alias("records"), F.sum("length").alias("bytes"))
    moved = files.mapInArrow(move, "temp string, name string, records bigint, bytes bigint").select("name", "records", "bytes")
    moved.write.mode("overwrite").parquet(f"{path}/_manifest")
    system, root = fs.FileSystem.from_uri(path)
    system.create_dir(f"{root}/_temporary", recursive=True)
    system.delete_dir(f"{root}/_temporary")
    system.open_output_stream(f"{root}/_SUCCESS").close()


def read_warc(spark, path: str) -> DataFrame:
    """(file, offset, length, kind, uri, payload, digest_ok) of every record: for round trips and users of the files."""

    def parse(batches):
        import zlib

        tx.low_memory()
        for batch in batches:
            for file, content in zip(batch.column("path").to_pylist(), batch.column("content").to_pylist()):
                rows, at = [], 0
                while at < len(content):
                    d = zlib.decompressobj(31)
                    data = d.decompress(content[at:])
                    size = len(content) - at - len(d.unused_data)
                    head, _, rest = data.partition(b"\r\n\r\n")
                    fields = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
                    block = rest[: int(fields["Content-Length"])]
                    payload = block.partition(b"\r\n\r\n")[2] if fields["WARC-Type"] == "response" else block
                    ok = fields["WARC-Block-Digest"] == sha1(block) and fields.get("WARC-Payload-Digest", sha1(payload)) == sha1(payload)
                    rows.append((file.rsplit("/", 1)[-1], at, size, fields["WARC-Type"], fields.get("WARC-Target-URI"), payload, ok))
                    at += size
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary(), pa.bool_()))], ["file", "offset", "length", "kind", "uri", "payload", "digest_ok"])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(path).select("path", "content")
    return files.mapInArrow(parse, "file string, offset bigint, length bigint, kind string, uri string, payload binary, digest_ok boolean")


def warc_path(spark) -> str:
    return fresh_path(spark, "warc")
