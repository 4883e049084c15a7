"""WARC archives and a Merkle fixity audit of their replicas.

Pages are written as WARC/1.1 files of gzip members, one member a record, with an index of
(file, record number, offset, length). An audit reads the index's ranges from a replica and hashes
them; hashes of consecutive ranges are hashed again, ``fanout`` at a time, up to one root per file
and one root per replica. Two replicas are compared from the roots down: only children of nodes
that differ are looked at, so equal replicas cost one comparison and a damaged record costs one
path.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import uuid
import zlib
from collections import deque
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import new_folder, stage, table, text_column

FANOUT = 16
#: The date of records that carry none; fixed, so that writing again gives the same bytes.
DATE = "1970-01-01T00:00:00Z"


def record(uri: str, payload: bytes, kind: str = "resource", content: str = "text/html; charset=utf-8", date: str = DATE) -> bytes:
    """One WARC record; its id and digest follow from its content."""
    digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
    name = uuid.UUID(bytes=hashlib.sha256(uri.encode() + b"\0" + payload).digest()[:16], version=4)
    uri = " ".join(uri.split())  # a header is one line
    head = f"WARC/1.1\r\nWARC-Type: {kind}\r\nWARC-Target-URI: {uri}\r\nWARC-Date: {date}\r\nWARC-Record-ID: <urn:uuid:{name}>\r\nWARC-Payload-Digest: sha1:{digest}\r\nContent-Type: {content}\r\nContent-Length: {len(payload)}\r\n\r\n"
    return head.encode() + payload + b"\r\n\r\n"


def parse_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of one uncompressed record; raises ValueError if it is malformed or fails its digest."""
    head, sep, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    if not sep or not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    headers = dict(x.split(": ", 1) for x in lines[1:])
    n = int(headers["Content-Length"])
    payload = rest[:n]
    if len(payload) < n:
        raise ValueError("record is cut short")
    want = headers.get("WARC-Payload-Digest", "")
    if want.startswith("sha1:") and base64.b32encode(hashlib.sha1(payload).digest()).decode() != want[5:]:
        raise ValueError("payload digest differs")
    return headers, payload


def write_warc(pages: DataFrame, folder: str, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """Write ``pages`` to ``folder``; returns the index (key, file, name, i, offset, length).

    One file per input partition. Null html is an empty payload, a null url an empty URI; repeated
    rows are repeated records. An empty table writes nothing.
    """
    src = pages.select(pages[key].alias("key"), pages[url].alias("url"), pages[html].alias("html"))
    kind = dict(src.dtypes)["key"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = pafs.FileSystem.from_uri(folder)
        store.create_dir(base, recursive=True)
        part = TaskContext.get().partitionId()
        name, out, at, i = f"{part:06d}-{uuid.uuid4().hex}.warc.gz", None, 0, 0
        for batch in batches:
            if out is None and batch.num_rows:
                out = store.open_output_stream(f"{base}/{name}", compression=None, buffer_size=1 << 20)
            offsets, lengths = [], []
            for u, h in zip(text_column(batch, "url"), text_column(batch, "html")):
                member = gzip.compress(record(u, h.encode("utf-8", "surrogatepass")), compresslevel=1, mtime=0)
                out.write(member)
                offsets.append(at)
                lengths.append(len(member))
                at += len(member)
            n = batch.num_rows
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array([part] * n, pa.int64()), pa.array([name] * n, pa.string()), pa.array(range(i, i + n), pa.int64()), pa.array(offsets, pa.int64()), pa.array(lengths, pa.int64())], names=["key", "file", "name", "i", "offset", "length"])
            i += n
        if out is not None:
            out.close()

    index = src.mapInArrow(run, f"key {kind}, file long, name string, i long, offset long, length long")
    return stage(index, "warc-index").withColumnRenamed("key", key)


def copy_replica(index: DataFrame, source: str, target: str, damage: Column | None = None) -> None:
    """Copy the files that an index names from one folder to another, a file a task.

    Where ``damage``, a condition on the index's columns, holds, the middle byte of the record's
    range comes out with its lowest bit turned: a replica to try an audit on.
    """
    broken = F.sort_array(F.collect_list(F.col("offset") + F.floor(F.col("length") / 2)))
    names = index.groupBy("name").agg((F.lit(None).cast("array<bigint>") if damage is None else broken).alias("at"))
    if damage is not None:
        hurt = index.filter(damage).groupBy("name").agg(broken.alias("at"))
        names = names.select("name").join(hurt, "name", "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, here = pafs.FileSystem.from_uri(source)
        b, there = pafs.FileSystem.from_uri(target)
        b.create_dir(there, recursive=True)
        for batch in batches:
            for name, wrong in zip(batch.column("name").to_pylist(), batch.column("at").to_pylist()):
                tmp = f"{there}/.{uuid.uuid4().hex}"
                with a.open_input_stream(f"{here}/{name}", compression=None) as f, b.open_output_stream(tmp, compression=None) as g:
                    done, todo = 0, deque(wrong or [])
                    while chunk := f.read(1 << 20):
                        if todo and todo[0] < done + len(chunk):
                            chunk = bytearray(chunk)
                            while todo and todo[0] < done + len(chunk):
                                chunk[todo.popleft() - done] ^= 1
                        g.write(bytes(chunk))
                        done += len(chunk)
                b.move(tmp, f"{there}/{name}")
            yield batch.select(["name"])

    names.select("name", "at").mapInArrow(run, "name string").write.format("noop").mode("overwrite").save()


def leaf_hashes(index: DataFrame, folder: str, key: str = "page_id", payloads: bool = False) -> DataFrame:
    """(key, file, i, offset, length, hash) of a replica's stored ranges, in index order.

    With ``payloads`` also payload_sha256 and payload_bytes, null where the record does not parse.
    A missing file or a short range gives the hash of what is there.
    """
    src = index.select(F.col(key).alias("key"), "file", "name", "i", "offset", "length")
    kind = dict(src.dtypes)["key"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = pafs.FileSystem.from_uri(folder)
        name, f = None, None
        for batch in batches:
            hashes, shas, sizes = [], [], []
            for n, at, size in zip(*(batch.column(c).to_pylist() for c in ("name", "offset", "length"))):
                if n != name:
                    if f is not None:
                        f.close()
                    name = n
                    try:
                        f = store.open_input_file(f"{base}/{n}")
                    except FileNotFoundError:
                        f = None
                raw = b""
                if f is not None and at < f.size():
                    f.seek(at)
                    raw = f.read(size)
                hashes.append(hashlib.sha256(raw).hexdigest())
                if payloads:
                    try:
                        payload = parse_record(gzip.decompress(raw))[1]
                        shas.append(hashlib.sha256(payload).hexdigest())
                        sizes.append(len(payload))
                    except (ValueError, OSError, EOFError, zlib.error):
                        shas.append(None)
                        sizes.append(None)
            cols = [batch.column(c) for c in ("key", "file", "i", "offset", "length")] + [pa.array(hashes, pa.string())]
            names = ["key", "file", "i", "offset", "length", "hash"]
            if payloads:
                cols += [pa.array(shas, pa.string()), pa.array(sizes, pa.int64())]
                names += ["payload_sha256", "payload_bytes"]
            yield pa.RecordBatch.from_arrays(cols, names=names)

    extra = ", payload_sha256 string, payload_bytes long" if payloads else ""
    return src.mapInArrow(run, f"key {kind}, file long, i long, offset long, length long, hash string{extra}").withColumnRenamed("key", key)


class MerkleTree:
    """Levels of a replica's tree: levels[0] are records, then ranges of files, then ranges of files' roots.

    A node is (file, node, start, stop, hash); from ``first_top`` on, file is 0 and nodes stand for
    runs of files. Every level is a small table a factor ``fanout`` below the one beneath it.
    """

    def __init__(self, leaves: DataFrame, fanout: int = FANOUT):
        self.fanout = fanout
        start = leaves.select("file", F.col("i").alias("node"), F.col("offset").alias("start"), (F.col("offset") + F.col("length")).alias("stop"), "hash")
        self.levels = [stage(start, "tree")]
        most = self.levels[0].agg(F.max("node").alias("i"), F.max("file").alias("f")).first()
        width = (most.i if most.i is not None else 0) + 1
        while width > 1:
            self.levels.append(stage(self._up(self.levels[-1], F.col("file"), F.floor(F.col("node") / fanout)), "tree"))
            width = -(-width // fanout)
        self.first_top = len(self.levels)
        files = (most.f if most.f is not None else 0) + 1
        low = self.levels[-1].select(F.lit(0).cast("long").alias("file"), F.col("file").alias("node"), "start", "stop", "hash")
        while True:
            low = stage(self._up(low, F.lit(0).cast("long"), F.floor(F.col("node") / fanout)), "tree")
            self.levels.append(low)
            files = -(-files // fanout)
            if files <= 1:
                break

    @staticmethod
    def _up(level: DataFrame, file, node) -> DataFrame:
        kids = F.array_sort(F.collect_list(F.struct("node", "hash")))
        keyed = level.select(file.alias("file"), node.cast("long").alias("up"), "node", "start", "stop", "hash")
        out = keyed.groupBy("file", "up").agg(kids.alias("kids"), F.min("start").alias("start"), F.max("stop").alias("stop"))
        text = F.concat_ws(",", F.transform("kids", lambda k: F.concat(k["node"].cast("string"), F.lit(":"), k["hash"])))
        return out.select("file", F.col("up").alias("node"), "start", "stop", F.sha2(text, 256).alias("hash"))

    def root(self) -> str | None:
        r = self.levels[-1].first()
        return r.hash if r else None


def compare_replicas(a: MerkleTree, b: MerkleTree) -> DataFrame:
    """(file, i, start, stop) of records that differ or exist in one replica only, by descending differing branches."""
    if a.fanout != b.fanout or len(a.levels) != len(b.levels):
        raise ValueError("replicas must be audited against one index")
    spark = a.levels[0].sparkSession
    none = spark.createDataFrame([], "file long, i long, start long, stop long")
    if a.root() == b.root():
        return none
    wrong = None
    for level in range(len(a.levels) - 1, -1, -1):
        x, y = a.levels[level], b.levels[level]
        if wrong is not None:
            top = level + 1 == a.first_top  # from a run of files into the files themselves
            parent = (F.lit(0).cast("long"), F.floor(F.col("file") / a.fanout)) if top else (F.col("file"), F.floor(F.col("node") / a.fanout))
            x, y = (t.withColumns({"pf": parent[0], "pn": parent[1].cast("long")}).join(wrong, ["pf", "pn"], "left_semi").drop("pf", "pn") for t in (x, y))
        x, y = (t.select("file", "node", *[F.col(c).alias(f"{c}_{s}") for c in ("start", "stop", "hash")]) for t, s in ((x, "a"), (y, "b")))
        diff = x.join(y, ["file", "node"], "full").filter(~F.col("hash_a").eqNullSafe(F.col("hash_b")))
        diff = stage(diff.select("file", "node", F.coalesce("start_a", "start_b").alias("start"), F.coalesce("stop_a", "stop_b").alias("stop")), "differs")
        wrong = diff.select(F.col("file").alias("pf"), F.col("node").alias("pn"))
    return diff.withColumnRenamed("node", "i")


#: Pages whose records the query damages in the second replica: this remainder of their id.
DAMAGED, OF = 7, 50


def op6_merkle_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Archive all ``pages``, copy the archive with known damage, audit both replicas; one row per page.

    ``intact`` and the damaged range come from the descent; the damage is known to the copy alone.
    """
    one, two = new_folder(spark, "warc"), new_folder(spark, "warc-copy")
    index = write_warc(table(spark, sf_dir, "pages").select("page_id", "url", "html"), one)
    copy_replica(index, one, two, F.pmod("page_id", F.lit(OF)) == DAMAGED)
    kept = stage(leaf_hashes(index, one, payloads=True), "audit")
    wrong = compare_replicas(MerkleTree(kept), MerkleTree(leaf_hashes(index, two)))
    wrong = wrong.select("file", "i", (F.col("stop") - F.col("start")).alias("damaged"))
    out = kept.join(wrong, ["file", "i"], "left")
    return out.select("page_id", "payload_sha256", "payload_bytes", F.col("damaged").isNull().alias("intact"), F.coalesce(F.col("damaged") == F.col("length"), F.lit(True)).alias("range_found"))


OP6_SQL = f"""
SELECT page_id, sha256(coalesce(html, '')) AS payload_sha256, strlen(coalesce(html, ''))::BIGINT AS payload_bytes,
    page_id % {OF} IS DISTINCT FROM {DAMAGED} AS intact, TRUE AS range_found
FROM pages
"""
