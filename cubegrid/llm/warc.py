"""WARC archives: a deterministic sharded writer with revisit records, and a streaming reader.

Records are dealt to shards by ranges of (page id, payload digest), cut where the sum of bytes in that
order passes a multiple of the shard size: the shards depend on the data alone, and neither far-off ids, nor
one id or no id on very many pages, makes a shard larger than that and one group of equal records. At most
``_MOST_SHARDS`` cuts of 17 bytes are broadcast (for more data the shards grow). Records are sorted within a shard, compressed one gzip member per record, and rolled into
a new file when the compressed size passes a limit. Headers, record ids and digests are made anew
from the content. Each attempt of a task writes temporary names of its own and reports them; the
reports are stored, and only files they name are renamed into place, so a lost executor, a retry
or a speculative copy leaves no half or double file. The manifest of final files is written last.

The archive folder must be one that pyarrow's file systems open on every executor (the shared
folder of the cluster is).

Defined results: null html is an empty payload; null url leaves out the target address; rows with
null page_id are written too (first), never referred to, and revisit the response of their payload
if it has one. Of repeated rows that are the response, the first is the response and the others
revisit it. An empty table gives no file.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid.fs import delete
from cubegrid.llm.common import join_hot, shared_path, slices, stored, tame_arrow

_NAMESPACE = uuid.UUID("5f1c1f86-6a0c-5d0e-9d4e-6c1a54b7a0c1")
_MANIFEST = "shard int, seq int, temp string, name string, records long, bytes long, sha256 string"
_MOST_SHARDS = 1 << 20
#: Bytes that headers add to a payload, about.
_HEAD_BYTES = 400


def _open(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


def record_id(page_id: int | None, sha1: bytes, nth: int) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMESPACE, f'{page_id}:{sha1.hex()}:{nth}')}>"


def _line(name: str, value: str) -> bytes:
    clean = re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", value) if name == "WARC-Target-URI" else value
    return f"{name}: {clean}\r\n".encode()


def build_record(page_id: int | None, url: str | None, payload: bytes, sha1: bytes, refers_to: int | None, revisit: bool, nth: int, date: str) -> bytes:
    """One uncompressed record with its trailing blank lines."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    head = [
        b"WARC/1.1\r\n",
        _line("WARC-Type", "revisit" if revisit else "response"),
        _line("WARC-Record-ID", record_id(page_id, sha1, nth)),
        _line("WARC-Date", date),
    ]
    if url is not None:
        head.append(_line("WARC-Target-URI", url))
    if page_id is not None:
        head.append(_line("X-Page-ID", str(page_id)))
    if revisit:
        head.append(_line("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))
        head.append(_line("WARC-Refers-To", record_id(refers_to, sha1, 0)))
        head.append(_line("X-Refers-To-Page-ID", str(refers_to)))
    head.append(_line("WARC-Payload-Digest", "sha1:" + base64.b32encode(sha1).decode()))
    head.append(_line("WARC-Block-Digest", "sha1:" + base64.b32encode(hashlib.sha1(block).digest()).decode()))
    head.append(_line("Content-Type", "application/http; msgtype=response"))
    head.append(_line("Content-Length", str(len(block))))
    return b"".join([*head, b"\r\n", block, b"\r\n\r\n"])


def _member(raw: bytes, level: int) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def _body(html: str) -> Column:
    return F.coalesce(F.col(f"`{html}`"), F.lit("")).cast("binary")


def record_keys(pages: DataFrame, page_id: str, html: str) -> DataFrame:
    """page_id, sha1 and payload bytes of every page: narrow, so it is stored and read as often as needed."""
    body = _body(html)
    return pages.select(F.col(f"`{page_id}`").cast("long").alias("page_id"), F.unhex(F.sha1(body)).alias("sha1"), F.octet_length(body).cast("long").alias("size"))


def assign_roles(pages: DataFrame, keys: DataFrame, page_id: str, url: str, html: str, min_bytes: int) -> DataFrame:
    """Two kinds of rows: kind 1 is a page (page_id, url, payload, sha1); kind 0 says for a page_id
    and sha1 which page holds the response of that payload (only where several pages have it).

    Both go through one shuffle, where a page meets its kind 0 row by sorting, so payloads move once.
    Groups are counted before they are joined back to narrow rows, and hot payloads are dealt in that join.
    """
    body = _body(html)
    rows = pages.select(F.col(f"`{page_id}`").cast("long").alias("page_id"), F.col(f"`{url}`").cast("string").alias("url"), body.alias("payload"), F.unhex(F.sha1(body)).alias("sha1"))
    narrow = keys.where(F.col("size") >= min_bytes).select("page_id", "sha1")
    groups = stored(narrow.groupBy("sha1").agg(F.max("page_id").alias("response"), F.count("*").alias("n")).where("n > 1"), "warc-groups")
    roles = join_hot(narrow, groups, ["sha1"], "n").select("page_id", F.lit(None).cast("string").alias("url"), F.lit(None).cast("binary").alias("payload"), "sha1", "response", F.lit(0).alias("kind"))
    return rows.select("*", F.lit(None).cast("long").alias("response"), F.lit(1).alias("kind")).unionByName(roles)


def order_keys(page_id: pa.Array, sha1: pa.Array) -> np.ndarray:
    """17 bytes per record that sort as (page id, nulls first; first eight bytes of the digest)."""
    none = page_id.is_null().to_numpy(zero_copy_only=False)
    ids = pc.fill_null(page_id, 0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)
    out = np.zeros((len(ids), 17), np.uint8)
    out[:, 0] = ~none
    out[:, 1:9] = np.where(none, np.uint64(0), ids).astype(">u8").view(np.uint8).reshape(-1, 8)
    out[:, 9:] = np.frombuffer(b"".join(x[:8] for x in sha1.to_pylist()), np.uint8).reshape(-1, 8)
    return out.view("S17").ravel()


def _cuts(keys: DataFrame, shard_bytes: int) -> np.ndarray:
    """The least key of every shard, in order (the first is the least of all)."""
    groups = keys.groupBy("page_id", "sha1").agg(F.sum(F.col("size") + _HEAD_BYTES).alias("size"))
    order = [F.asc_nulls_first("page_id"), F.col("sha1")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        before, part = 0, TaskContext.get().partitionId()
        for b in batches:
            size = b.column("size").to_numpy(zero_copy_only=False)
            run_ = before + np.cumsum(size) - size
            before += int(size.sum())
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(size), part)), b.column("page_id"), b.column("sha1"), b.column("size"), pa.array(run_)], names=["part", "page_id", "sha1", "size", "before"])

    ordered = stored(groups.repartitionByRange(*order).sortWithinPartitions(*order).select("page_id", "sha1", "size").mapInArrow(run, "part long, page_id long, sha1 binary, size long, before long"), "warc-order")
    parts = sorted((r[0], r[1]) for r in ordered.groupBy("part").agg(F.sum("size")).collect())  # one row per partition
    total = sum(n for _, n in parts)
    if not total:
        return np.zeros(0, "S17")
    offsets, at = [], 0
    for part, n in parts:
        offsets.append((part, at))
        at += n
    first = keys.sparkSession.createDataFrame(offsets, "part long, first long")  # one row per partition again
    span = max(shard_bytes, -(-total // _MOST_SHARDS))
    shard = F.expr(f"(first + before) div {span}")
    least = ordered.join(F.broadcast(first), "part").groupBy(shard.alias("shard")).agg(F.min(F.struct("page_id", "sha1")).alias("k"))
    found = least.select("shard", "k.page_id", "k.sha1").toArrow()  # _MOST_SHARDS rows at most
    return np.sort(order_keys(found.column("page_id").combine_chunks(), found.column("sha1").combine_chunks()))


def write(pages: DataFrame, path: str, page_id: str = "page_id", url: str = "url", html: str = "html", min_bytes: int = 0, shard_bytes: int = 64 << 20, roll_bytes: int = 16 << 20, level: int = 6, date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """Write archives under ``path`` and return the manifest: one row per file, final and complete."""
    spark = pages.sparkSession
    tame_arrow(spark)
    keys = stored(record_keys(pages, page_id, html), "warc-keys")
    rows = assign_roles(pages, keys, page_id, url, html, min_bytes)
    cuts = _cuts(keys, shard_bytes)
    shared = spark.sparkContext.broadcast(cuts)

    @F.arrow_udf("int")
    def shard_of(page: pa.Array, sha1: pa.Array) -> pa.Array:
        return pa.array(np.maximum(np.searchsorted(shared.value, order_keys(page, sha1), side="right") - 1, 0), pa.int32())

    dealt = rows.withColumn("shard", shard_of("page_id", "sha1")).repartitionById(max(1, len(cuts)), F.col("shard")).sortWithinPartitions("shard", F.asc_nulls_first("page_id"), "sha1", "kind", "url")
    temp = f"{path}/_temporary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, root = _open(temp)
        system.create_dir(root, recursive=True)
        attempt = uuid.uuid4().hex
        out = None
        state: dict = {}
        done = []

        def close() -> None:
            nonlocal out
            if out is not None:
                out.close()
                done.append((state["shard"], state["seq"], f"{temp}/{state['temp']}", f"part-{state['shard']:06d}-{state['seq']:05d}.warc.gz", state["records"], state["bytes"], state["sha"].hexdigest()))
                out = None

        def put(data: bytes, records: int) -> None:
            out.write(data)
            state["bytes"] += len(data)
            state["records"] += records
            state["sha"].update(data)

        last, nth = None, 0
        said, response = None, None  # the latest kind 0 row
        for part in slices(batches, "payload"):
            for r in part.to_pylist():
                key = (r["page_id"], r["sha1"])
                if r["kind"] == 0:
                    said, response = key, r["response"]
                    continue
                if out is not None and (state["bytes"] >= roll_bytes or r["shard"] != state["shard"]):
                    close()
                if out is None:
                    seq = state["seq"] + 1 if state.get("shard") == r["shard"] else 0
                    state = {"shard": r["shard"], "seq": seq, "temp": f"{r['shard']:06d}-{seq:05d}-{attempt}", "records": 0, "bytes": 0, "sha": hashlib.sha256()}
                    out = system.open_output_stream(f"{root}/{state['temp']}", compression=None)
                    info = b"software: cubegrid\r\nformat: WARC File Format 1.1\r\n"
                    head = b"WARC/1.1\r\nWARC-Type: warcinfo\r\nWARC-Record-ID: <urn:uuid:%s>\r\nWARC-Date: %s\r\nContent-Type: application/warc-fields\r\nContent-Length: %d\r\n\r\n" % (str(uuid.uuid5(_NAMESPACE, f"info:{r['shard']}:{seq}")).encode(), date.encode(), len(info))
                    put(_member(head + info + b"\r\n\r\n", level), 0)
                nth = nth + 1 if key == last else 0
                last = key
                to = response if key == said else None
                revisit = to is not None and (r["page_id"] != to or nth > 0)
                put(_member(build_record(r["page_id"], r["url"], r["payload"], r["sha1"], to, revisit, nth, date), level), 1)
        close()
        if done:
            kinds = [pa.int32(), pa.int32(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array([d[i] for d in done], kinds[i]) for i in range(7)], names=["shard", "seq", "temp", "name", "records", "bytes", "sha256"])

    reports = f"{path}/_reports"
    dealt.select("shard", "page_id", "url", "payload", "sha1", "response", "kind").mapInArrow(run, _MANIFEST).write.parquet(reports)

    def publish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        system, root = _open(path)
        for b in batches:
            for old, name in zip(b.column("temp").to_pylist(), b.column("name").to_pylist(), strict=True):
                _, old = _open(old)
                if system.get_file_info(f"{root}/{name}").type == fs.FileType.NotFound:  # else an earlier attempt has moved it
                    system.move(old, f"{root}/{name}")
            yield b

    manifest = f"{path}/_manifest"
    spark.read.schema(_MANIFEST).parquet(reports).mapInArrow(publish, _MANIFEST).select("shard", "seq", F.concat(F.lit(f"{path}/"), "name").alias("path"), "records", "bytes", "sha256").write.parquet(manifest)
    delete(spark, temp)
    delete(spark, reports)
    return spark.read.parquet(manifest)


# ---- reading ------------------------------------------------------------------------------------


def members(stream, chunk: int = 1 << 20) -> Iterator[tuple[int, bytes]]:
    """(offset, content) of each gzip member of a stream."""
    rest, at = b"", 0
    while True:
        rest = rest or stream.read(chunk)
        if not rest:
            return
        z = zlib.decompressobj(31)
        parts, used = [], 0
        while not z.eof:
            if not rest:
                rest = stream.read(chunk)
                if not rest:
                    raise EOFError("the archive ends within a record")
            parts.append(z.decompress(rest))
            used += len(rest) - len(z.unused_data)
            rest = z.unused_data
        yield at, b"".join(parts)
        at += used


def parse_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    fields = dict(x.split(": ", 1) for x in lines[1:] if ": " in x)
    return fields, rest[: int(fields["Content-Length"])]


_RECORDS = "path string, record_offset long, record_type string, record_id string, page_id long, url string, refers_to long, payload_digest string, payload_bytes long, payload binary"


def read(manifest: DataFrame) -> DataFrame:
    """Responses and revisits of the archives that ``manifest`` lists (column path), as a stream."""
    tame_arrow(manifest.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in _RECORDS.split(", ")]
        kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}
        types = [kinds[x.split()[1]] for x in _RECORDS.split(", ")]

        def flush(rows: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], types[i]) for i in range(len(names))], names=names)

        for b in batches:
            for path in b.column("path").to_pylist():
                system, own = _open(path)
                rows, size = [], 0
                with system.open_input_stream(own, compression=None) as stream:
                    for at, raw in members(stream):
                        f, block = parse_record(raw)
                        if f["WARC-Type"] not in ("response", "revisit"):
                            continue
                        head, _, payload = block.partition(b"\r\n\r\n")
                        length = int(re.search(rb"(?i)content-length: (\d+)", head)[1])
                        revisit = f["WARC-Type"] == "revisit"
                        page, to = f.get("X-Page-ID"), f.get("X-Refers-To-Page-ID")
                        rows.append((path, at, f["WARC-Type"], f["WARC-Record-ID"], int(page) if page else None, f.get("WARC-Target-URI"), int(to) if to else None, f["WARC-Payload-Digest"].removeprefix("sha1:"), length, None if revisit else payload))
                        size += len(raw)
                        if size > 4 << 20:
                            yield flush(rows)
                            rows, size = [], 0
                if rows:
                    yield flush(rows)

    files = manifest.select("path").repartition(max(1, manifest.sparkSession.sparkContext.defaultParallelism), "path")
    return files.mapInArrow(run, _RECORDS)


def with_digests(records: DataFrame) -> DataFrame:
    """Digest and size of each payload as read: of a response from its bytes, of a revisit as recorded."""

    @F.arrow_udf("string")
    def base32(sha1: pa.Array) -> pa.Array:
        return pa.array([None if x is None else base64.b32encode(x).decode() for x in sha1.to_pylist()], pa.string())

    here = base32(F.unhex(F.sha1("payload")))
    return records.withColumn("payload_digest", F.coalesce(here, "payload_digest")).withColumn("payload_bytes", F.coalesce(F.octet_length("payload").cast("long"), "payload_bytes"))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write every page to archives and read them back: digests, record type and what revisits refer to."""
    from cubegrid.llm.common import table

    manifest = write(table(spark, sf_dir, "pages"), shared_path(spark, "warc"))
    return with_digests(read(manifest)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
