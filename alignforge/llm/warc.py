"""Operator 4: WARC writing, external merge of the capture index, and reading back.

Every task writes one run: its captures sorted by URL key and timestamp, as gzip members of a WARC
archive, and their index lines in the same order. The runs' indexes are then merged: key ranges of about
RANGE entries are cut over all of them, however many there are, and each range pulls its slice of every run
through a loser tree, so the index is in global order without a run ever being sorted again. The merged
index tells which byte ranges to read.

Of equal payloads of at least 100 bytes, the smallest page_id is the response and the others revisit it.
Defined results: a null html is an empty payload, a null url an empty key; a row without page_id may
revisit but is no target while another row of the payload has one; rows that repeat the smallest page_id
are responses too; no rows make no archive. Extra columns are ignored. The pages table has no capture
time: it is page_id seconds after a fixed instant.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from datetime import datetime, timedelta, timezone
from math import ceil

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, lean_batches

SMALL = 100
#: Rows of one digest beyond which it is looked up in a broadcast, and most such digests that are broadcast.
HOT, HOT_MOST = 2_000, 100_000
#: Index entries that one range of the merge holds.
RANGE = 50_000
EPOCH = datetime(2020, 1, 1, tzinfo=timezone.utc)
#: Compressed bytes that one reading task takes from an archive.
SEGMENT = 8 << 20
LEVEL = 3
INDEX = "run int, seq long, url_key string, ts string, page_id long, file string, offset long, length long, record_type string"


def url_key(url: Column) -> Column:
    """Host labels reversed and comma-joined, then the rest, lower-cased."""
    bare = F.regexp_replace(F.lower(F.coalesce(url, F.lit(""))), r"^[a-z][a-z0-9+.-]*://", "")
    host, rest = F.regexp_extract(bare, r"^([^/?#:]*)", 1), F.regexp_replace(bare, r"^[^/?#]*", "")
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), ","), F.lit(")"), rest)


def decided(pages: DataFrame) -> DataFrame:
    """page_id, url, payload, digest, refers_to (null for a response). Minima are pre-aggregated; html moves once.

    Payloads under SMALL bytes look nothing up. Digests of more than HOT rows, of which there are at most rows / HOT,
    are looked up in a broadcast as long as that is bounded; both kinds are dealt by row, the others by digest.
    """
    body = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", body.alias("payload"), F.sha2(body, 256).alias("digest"))
    per = rows.where(F.octet_length("payload") >= SMALL).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n"))
    per = Scratch(pages.sparkSession, "digests").save(per.where("n > 1"), "digests")
    hot = per.where(F.col("n") > HOT).select(F.col("digest").alias("h_digest"), F.col("first_id").alias("h_first"))
    few = hot.count() <= HOT_MOST
    if few:
        rows = rows.join(F.broadcast(hot), F.col("digest") == F.col("h_digest"), "left")
    else:
        rows = rows.withColumn("h_digest", F.lit(None).cast("string")).withColumn("h_first", F.lit(None).cast("long"))
    alone = (F.octet_length("payload") < SMALL) | F.col("h_digest").isNotNull()
    rows = rows.withColumn("deal", F.when(alone, F.concat(F.lit("row "), F.xxhash64("page_id", "url").cast("string"))).otherwise(F.col("digest")))
    seen = per.where(F.col("n") <= HOT if few else F.lit(True)).select(F.col("digest").alias("s_digest"), "first_id")
    first = F.coalesce("h_first", "first_id")
    same = first.isNull() | F.coalesce(F.col("page_id") == first, F.lit(False))
    return rows.join(seen.hint("shuffle_hash"), F.col("deal") == F.col("s_digest"), "left").select("page_id", "url", "payload", "digest", F.when(same, F.lit(None)).otherwise(first).alias("refers_to"))


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, date: str) -> bytes:
    """One WARC 1.1 record: a response with its payload, or a revisit with the same HTTP head and no body."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head + payload if refers_to is None else head
    fields = [
        "WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Date: {date}", f"WARC-Target-URI: {' '.join((url or '').split())}", f"WARC-Payload-Digest: sha256:{digest}", "Content-Type: application/http; msgtype=response",
    ]
    if refers_to is not None:
        fields += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    return "\r\n".join([*fields, f"Content-Length: {len(block)}", "", ""]).encode() + block + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[int | None, int, str, str, int | None]:
    """page_id, payload bytes, digest, record type, refers_to; a response's payload is hashed anew and must agree."""
    top, _, block = raw.partition(b"\r\n\r\n")
    field = dict(line.split(": ", 1) for line in top.decode().split("\r\n")[1:])
    block = block[: int(field["Content-Length"])]
    head, _, payload = block.partition(b"\r\n\r\n")
    size = int(next(x for x in head.split(b"\r\n") if x.startswith(b"Content-Length: "))[16:])
    urn = lambda x: int(x[10:-1]) if len(x) > 11 else None
    digest = field["WARC-Payload-Digest"].removeprefix("sha256:")
    if field["WARC-Type"] == "response" and (len(payload) != size or hashlib.sha256(payload).hexdigest() != digest):
        raise ValueError(f"damaged record {field['WARC-Record-ID']}")
    return urn(field["WARC-Record-ID"]), size, digest, field["WARC-Type"], urn(field["WARC-Refers-To"]) if "WARC-Refers-To" in field else None


def _files(root: str):
    """The file system of a folder, and the folder's path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(root)


def write_runs(pages: DataFrame, root: str) -> DataFrame:
    """Writes one archive per task and returns the index entries (INDEX), each run in its own order.

    Every attempt writes an archive of its own name and only its own index lines name it, so a retry, a second
    attempt or a lost executor can't change bytes that other lines point to. archive() removes what no line names.
    """

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = _files(root)
        task = TaskContext.get()
        run, name = task.partitionId(), f"run-{task.partitionId():06d}-{task.taskAttemptId()}.warc.gz"
        lines, out, offset, seq = [], None, 0, 0
        for batch in batches:
            for page, url, payload, digest, refers, key, ts in zip(*(c.to_pylist() for c in batch.columns)):
                if out is None:
                    store.create_dir(base, recursive=True)
                    out = store.open_output_stream(f"{base}/{name}", compression=None)  # the members are packed already
                date = (EPOCH + timedelta(seconds=(page or 0) % (1 << 32))).strftime("%Y-%m-%dT%H:%M:%SZ")
                pack = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
                data = pack.compress(record(page, url, payload, digest, refers, date)) + pack.flush()
                out.write(data)
                lines.append((run, seq, key, ts, page, name, offset, len(data), "response" if refers is None else "revisit"))
                offset, seq = offset + len(data), seq + 1
                if len(lines) >= 10_000:
                    yield _lines(lines)
                    lines = []
        if out is not None:
            out.close()
        if lines:
            yield _lines(lines)

    ts = F.lpad(F.pmod(F.coalesce("page_id", F.lit(0)), F.lit(1 << 32)).cast("string"), 10, "0")
    rows = decided(pages).select("page_id", "url", "payload", "digest", "refers_to", url_key(F.col("url")).alias("url_key"), ts.alias("ts"))
    return rows.sortWithinPartitions("url_key", "ts", "page_id", "digest", "url").mapInArrow(write, INDEX)


def _lines(lines: list[tuple]) -> pa.RecordBatch:
    kinds = [("run", pa.int32()), ("seq", pa.int64()), ("url_key", pa.string()), ("ts", pa.string()), ("page_id", pa.int64()), ("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("record_type", pa.string())]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, (_, k) in zip(zip(*lines), kinds)], [n for n, _ in kinds])


class LoserTree:
    """Merges sorted iterators of (key, ...) tuples; each step replays one path of log2(k) matches."""

    def __init__(self, runs: list[Iterator[tuple]]):
        self.runs, self.n = runs, max(1, len(runs))
        self.head = [next(r, None) for r in runs] or [None]
        self.loser = [-1] * self.n
        for k in range(self.n):
            self._replay(k)

    def _beats(self, a: int, b: int) -> bool:
        x, y = self.head[a], self.head[b]
        return y is None if x is None or y is None else (x, a) < (y, b)

    def _replay(self, k: int) -> None:
        node, winner = (k + self.n) // 2, k
        while node:
            if self.loser[node] == -1:  # the first to arrive waits
                self.loser[node], winner = winner, -1
                break
            if self._beats(self.loser[node], winner):
                self.loser[node], winner = winner, self.loser[node]
            node //= 2
        if winner != -1:
            self.top = winner

    def __iter__(self) -> Iterator[tuple]:
        while self.head[self.top] is not None:
            k = self.top
            yield self.head[k]
            self.head[k] = next(self.runs[k], None)
            self._replay(k)


def merge_runs(entries: DataFrame, ranges: int) -> DataFrame:
    """Entries in global order of (url_key, ts, page_id, run, seq): partition by partition, row by row.

    Range cuts are Spark's; inside a range, rows are put by (run, seq), which restores each run's own
    order, and the runs are merged by a loser tree. run and seq are in the key, so what repeats one is cut too.
    """

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs: dict[int, list[tuple]] = {}
        schema = None
        for batch in batches:
            schema = batch.schema
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                key = (row[2], row[3], -1 if row[4] is None else row[4])
                runs.setdefault(row[0], []).append((key, row[1], row))
        done: list[tuple] = []
        for _, _, row in LoserTree([iter(r) for r in runs.values()]):
            done.append(row)
            if len(done) >= 10_000:
                yield _lines(done)
                done = []
        if done:
            yield _lines(done)
        assert schema is None or len(schema) == 9

    cut = entries.repartitionByRange(ranges, "url_key", "ts", F.coalesce("page_id", F.lit(-1)), "run", "seq")
    return cut.sortWithinPartitions("run", "seq").mapInArrow(merge, INDEX)


def read_back(index: DataFrame, root: str, tasks: int) -> DataFrame:
    """Reads every record that the index names: page_id, payload_bytes, payload_digest, record_type, refers_to.

    Entries are grouped to byte ranges of at most about SEGMENT bytes; a task streams one range at a time.
    """

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = _files(root)
        for batch in batches:
            for name, start, stop in zip(batch.column("file").to_pylist(), batch.column("start").to_pylist(), batch.column("stop").to_pylist()):
                with store.open_input_file(f"{base}/{name}") as f:
                    f.seek(start)
                    left, unzip, got, raw = stop - start, zlib.decompressobj(31), [], bytearray()
                    data = b""
                    while left or data:
                        if not data:
                            data = f.read(min(left, 1 << 20))
                            left -= len(data)
                            if not data:
                                raise ValueError(f"{name} ends early")
                        raw += unzip.decompress(data)
                        data = unzip.unused_data
                        if unzip.eof:
                            got.append(parse(bytes(raw)))
                            unzip, raw = zlib.decompressobj(31), bytearray()
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(c, k) for c, k in zip(zip(*got), (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()))],
                        ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"],
                    )

    parts = index.groupBy("file", F.floor(F.col("offset") / SEGMENT).alias("part")).agg(F.min("offset").alias("start"), F.max(F.col("offset") + F.col("length")).alias("stop"))
    spread = parts.select("file", "start", "stop").repartition(tasks, "file", "start")
    return spread.mapInArrow(read, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive(pages: DataFrame, root: str | None = None) -> tuple[DataFrame, str]:
    """Writes the archives and the merged index below root; returns the index and the archives' folder."""
    spark, scratch = pages.sparkSession, Scratch(pages.sparkSession, "warc")
    root = root or scratch.path("archives")
    with lean_batches(spark):
        runs = scratch.save(write_runs(pages, root), "runs")
    _sweep(spark, runs, root)
    index = scratch.save(merge_runs(runs, _at_least(spark, runs.count() / RANGE)), "index")
    scratch.drop("runs")
    return index, root


def _at_least(spark: SparkSession, wanted: float) -> int:
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), ceil(wanted))


def _sweep(spark: SparkSession, runs: DataFrame, root: str) -> None:
    """Removes archives of attempts whose lines were not kept; file names are one a task."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(root)
    store = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not store.exists(folder):
        return
    named = {r["file"] for r in runs.select("file").distinct().toLocalIterator()}
    for entry in store.listStatus(folder):
        if entry.getPath().getName() not in named:
            store.delete(entry.getPath(), False)


def round_trip(pages: DataFrame) -> DataFrame:
    """One row per page, as read from the archives."""
    index, root = archive(pages)
    size = index.agg(F.sum("length")).first()[0] or 0
    return read_back(index, root, _at_least(pages.sparkSession, size / (4 * SEGMENT)))
