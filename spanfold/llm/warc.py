"""Deterministic sharded WARC writer and reader."""

from __future__ import annotations

import base64
import gzip
import hashlib
import json
import math
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfold.llm.common import lean, shared_dir, ship, written

ROLL_BYTES = 16 << 20  # compressed size at which a file is closed
SHARD_BYTES = 24 << 20  # payload bytes of a shard, about, for as many shards as SAMPLE allows
PER_SHARD = 4  # ids sampled for each shard
SAMPLE = 1 << 22  # ids read by the driver to cut the key range, 8 bytes each, at most about
HOT_COPIES = 1 << 16  # pages that share a payload beyond which its row is broadcast
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _member(headers: list[tuple[str, str]], block: bytes) -> bytes:
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in headers) + f"Content-Length: {len(block)}\r\n\r\n"
    return gzip.compress(head.encode() + block + b"\r\n\r\n", compresslevel=6, mtime=0)


def _urn(*what) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '/'.join(map(str, what)))}>"


def _one_line(text: str) -> str:
    return "".join(c if c > " " else f"%{ord(c):02X}" for c in text)


def record(page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    """One gzip member: a response, or a revisit whose block has the response's headers only."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    headers = [("WARC-Type", "response" if refers_to is None else "revisit"), ("WARC-Record-ID", _urn("page", page_id, digest)), ("WARC-Date", DATE)]
    headers += [("WARC-Target-URI", _one_line(url) if url else f"urn:page:{page_id}"), ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    if page_id is not None:
        headers.append(("WARC-Page-ID", str(page_id)))
    if refers_to is not None:
        headers += [("WARC-Profile", PROFILE), ("WARC-Refers-To", _urn("page", refers_to, digest)), ("WARC-Refers-To-Page-ID", str(refers_to))]
    return _member(headers, http + (payload if refers_to is None else b""))


def members(stream):
    """Uncompressed gzip members of a stream, one at a time."""
    unzip, held, data = zlib.decompressobj(31), [], b""
    while True:
        data = data or stream.read(1 << 20)
        if not data:
            if held:
                raise ValueError("truncated archive")
            return
        held.append(unzip.decompress(data))
        data = b""
        if unzip.eof:
            data = unzip.unused_data
            yield b"".join(held)
            unzip, held = zlib.decompressobj(31), []


class Summed:
    """A stream whose bytes are hashed as they are read."""

    def __init__(self, stream):
        self.stream, self.sha = stream, hashlib.sha256()

    def read(self, n: int) -> bytes:
        data = self.stream.read(n)
        self.sha.update(data)
        return data


def parse_record(raw: bytes) -> tuple[dict, bytes]:
    head, _, rest = raw.partition(b"\r\n\r\n")
    headers = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    return headers, rest[: int(headers["Content-Length"])]


def write_archives(pages: DataFrame, target: str | None = None, least_bytes: int = 0, roll_bytes: int = ROLL_BYTES) -> tuple[str, DataFrame]:
    """Write every row of pages (page_id, url, html) as a WARC record; (folder, manifest rows).

    The payload is the html in UTF-8 (null: empty). Of records with equal payloads of at least
    `least_bytes` bytes, the one with the largest page_id is a response and others revisit it. Rows
    that repeat the largest page_id are responses each; a null page_id is never the largest unless
    all are null. Other columns are ignored. The archives depend on the rows alone: shards are cut
    at ids of a hash sample, records go in id order, files roll at a compressed size, and digests,
    record ids and dates are regenerated. A task writes one shard, under a name of its own, and
    renames when a file is whole, so a task that runs twice leaves the same files; names of attempts
    that failed are removed at the end. The manifest, a line a file (name, records, bytes, SHA-256),
    comes before `manifest.json`, which has the totals and says that the archive is whole.

    Shards have SHARD_BYTES of payload up to 2^20 of them (25 TB) and grow with the input from there
    (100 MB at 100 TB); a shard is streamed, never held.
    """
    spark = pages.sparkSession
    target = (target or f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}").rstrip("/")
    rows = pages.select(F.col("page_id").cast("long").alias("id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary").alias("payload"))
    facts = rows.agg(F.count("*").alias("n"), F.sum(F.octet_length("payload")).alias("size")).first()
    shards = max(1, min(SAMPLE // PER_SHARD, math.ceil((facts["size"] or 0) / SHARD_BYTES)))
    every = max(1, facts["n"] // min(SAMPLE, max(1024, PER_SHARD * shards)))
    sampled = rows.where(F.col("id").isNotNull() & (F.pmod(F.xxhash64("id"), F.lit(every)) == 0)).select("id").toArrow()
    sample = np.unique(sampled.column("id").to_numpy())
    cuts = np.unique(sample[len(sample) * np.arange(1, shards) // shards]) if len(sample) else sample

    light = rows.select("id", F.sha1("payload").alias("sha"), F.octet_length("payload").alias("size"))
    last = light.where(F.col("size") >= least_bytes).groupBy("sha", "size").agg(F.max("id").alias("last"), F.count("*").alias("copies")).where("copies > 1 and last is not null")
    last = written(last, "payload-copies")
    # a payload of many pages would send them all to one task: such payloads are few (one in HOT_COPIES pages at most) and broadcast
    crowded = F.broadcast(last.where(F.col("copies") > HOT_COPIES).drop("copies"))
    met = light.join(crowded, ["sha", "size"]).unionByName(light.join(crowded, ["sha", "size"], "left_anti").join(last.drop("copies"), ["sha", "size"]))
    roles = met.where("id is null or id < last").select("id", "sha", "last").distinct()

    def shards_of(ids):
        return pa.array(np.where(ids.is_null().to_numpy(zero_copy_only=False), 0, np.searchsorted(cuts, ids.fill_null(0).to_numpy(), side="right")).astype(np.int32))

    def deal(batches):
        for batch in batches:
            sha = [hashlib.sha1(b.as_buffer()).hexdigest() for b in batch.column(2)]
            n = len(sha)
            yield pa.record_batch([shards_of(batch.column(0)), batch.column(0), pa.array(sha), pa.nulls(n, pa.int64()), batch.column(1), batch.column(2)], names=["shard", "id", "sha", "last", "url", "payload"])

    def deal_roles(batches):
        for batch in batches:
            n = batch.num_rows
            yield pa.record_batch([shards_of(batch.column(0)), batch.column(0), batch.column(1), batch.column(2), pa.nulls(n, pa.string()), pa.nulls(n, pa.binary())], names=["shard", "id", "sha", "last", "url", "payload"])

    shape = "shard int, id long, sha string, last long, url string, payload binary"

    def write(batches):
        store, root = pafs.FileSystem.from_uri(target)
        store.create_dir(root, recursive=True)
        done, state = [], {}

        def close():
            if state:
                state["out"].close()
                store.move(state["temp"], f"{root}/{state['name']}")
                done.append((state["name"], state["records"], state["bytes"], state["sha"].hexdigest()))
                state.clear()

        def put(data: bytes):
            state["out"].write(data)
            state["sha"].update(data)
            state["bytes"] += len(data)

        def start(shard, number):
            name = f"pages-{shard:05d}-{number:05d}.warc.gz"
            temp = f"{root}/.{name}.{uuid.uuid4().hex}"
            state.update(out=store.open_output_stream(temp, compression=None), temp=temp, name=name, records=0, bytes=0, sha=hashlib.sha256(), shard=shard, number=number)
            put(_member([("WARC-Type", "warcinfo"), ("WARC-Record-ID", _urn("file", name)), ("WARC-Date", DATE), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n"))

        role = None
        for batch in batches:
            for shard, page, sha, last_id, url, payload in zip(*(batch.column(i) for i in range(6))):
                if last_id.is_valid:  # sorts just before the pages it speaks of
                    role = (page.as_py(), sha.as_py(), last_id.as_py())
                    continue
                shard, page, sha, data = shard.as_py(), page.as_py(), sha.as_py(), payload.as_py()
                if not state or state["shard"] != shard:
                    close()
                    start(shard, 0)
                elif state["bytes"] >= roll_bytes:
                    number = state["number"] + 1
                    close()
                    start(shard, number)
                digest = base64.b32encode(bytes.fromhex(sha)).decode()
                put(record(page, url.as_py(), data, digest, role[2] if role and role[:2] == (page, sha) else None))
                state["records"] += 1
        close()
        if done:
            yield pa.record_batch([pa.array(x) for x in zip(*done)], names=["file", "records", "bytes", "sha256"])

    every_row = rows.mapInArrow(deal, shape).unionByName(roles.mapInArrow(deal_roles, shape))
    dealt = every_row.repartitionById(len(cuts) + 1, "shard").sortWithinPartitions("shard", "id", "sha", F.col("last").desc_nulls_last(), "url")
    manifest = written(dealt.mapInArrow(lean(write), "file string, records long, bytes long, sha256 string"), "warc-manifest")
    store, root = pafs.FileSystem.from_uri(target)
    store.create_dir(root, recursive=True)
    for name in (f for f in store.get_file_info(pafs.FileSelector(root)) if f.base_name.startswith(".pages-")):
        store.delete_file(name.path)
    manifest.write.mode("overwrite").json(f"{target}/manifest")
    total = manifest.agg(F.count("*").alias("files"), F.sum("records").alias("records"), F.sum("bytes").alias("bytes")).first()
    with store.open_output_stream(f"{root}/.manifest.json.tmp") as out:
        out.write(json.dumps({"files": total.files, "records": total.records or 0, "bytes": total.bytes or 0, "list": "manifest"}).encode())
    store.move(f"{root}/.manifest.json.tmp", f"{root}/manifest.json")
    return target, manifest


def listed(spark, target: str) -> DataFrame:
    """The manifest of a finished archive, as written beside its files."""
    return spark.read.schema("file string, records long, bytes long, sha256 string").json(f"{target}/manifest")


def read_archives(target: str, manifest: DataFrame) -> DataFrame:
    """Records of the files a manifest lists: page_id, url, payload_bytes, payload_digest,
    record_type, refers_to, payload (null in revisits). A file's bytes and SHA-256 are checked
    against the manifest, digests of responses against their payloads."""

    def read(batches):
        store, root = pafs.FileSystem.from_uri(target)
        names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
        types = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]

        def batch_of(out):
            return pa.record_batch([pa.array(x, t) for x, t in zip(zip(*out), types)], names=names)

        for batch in batches:
            for name, whole in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                out, room = [], 0
                with store.open_input_stream(f"{root}/{name}", compression=None) as source:
                    stream = Summed(source)
                    for raw in members(stream):
                        headers, block = parse_record(raw)
                        kind = headers["WARC-Type"]
                        if kind == "warcinfo":
                            continue
                        http, _, body = block.partition(b"\r\n\r\n")
                        size = next(int(x.split(b": ")[1]) for x in http.split(b"\r\n") if x.startswith(b"Content-Length: "))
                        digest = headers["WARC-Payload-Digest"].removeprefix("sha1:")
                        if kind == "response" and (len(body) != size or base64.b32encode(hashlib.sha1(body).digest()).decode() != digest):
                            raise ValueError(f"{name}: payload of {headers['WARC-Record-ID']} is damaged")
                        page, refers = headers.get("WARC-Page-ID"), headers.get("WARC-Refers-To-Page-ID")
                        out.append((None if page is None else int(page), headers["WARC-Target-URI"], size, digest, kind, None if refers is None else int(refers), body if kind == "response" else None))
                        room += len(body)
                        if room > 8 << 20:
                            yield batch_of(out)
                            out, room = [], 0
                if stream.sha.hexdigest() != whole:
                    raise ValueError(f"{name}: the file is not the one the manifest lists")
                if out:
                    yield batch_of(out)

    shape = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    files = manifest.count()  # names are short: without a number they would all be merged into one task
    return manifest.select("file", "sha256").repartition(max(1, min(files, 100_000)), "file").mapInArrow(lean(read), shape)


ship(__name__)
