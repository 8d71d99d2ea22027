"""WARC archives and their capture index.

``write_archives`` makes one record per row, gzipped by itself, in archives that
follow the tasks; an archive is the concatenation of its rows' ``data`` by
``offset``.  Of records with equal payloads the one with the smallest id is a
response, others are revisits that refer to it and hold the HTTP head only.
``read_archives`` parses the stored bytes again and verifies digests.

``merge_index`` orders captures by URL key and time over all archives: each
archive task's captures are a sorted run; runs are cut at range borders into
blocks; each range merges its runs' blocks with a loser tree, opening a block
only when its first key is due, so that a task holds the blocks that overlap.

Defined results: a null payload is an empty one; a null URL has the key "" and
target ``urn:none``; rows of the same id and payload as the response are
responses too, so repeated rows repeat; rows with a null id refer to the
smallest id of equal payload, and are responses where there's none.  Only the
columns named are read.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
from collections.abc import Callable, Iterator
from datetime import UTC, datetime, timedelta

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship_package, written
from .bitmap import among

RECORD = "archive string, offset long, data binary"
CAPTURE = "id long, url string, url_key string, time string, record_type string, payload_bytes long, payload_digest string, refers_to long, archive string, offset long, length long, payload binary"
BLOCK = 2048


def url_key(url: str | None) -> str:
    """Host labels from the top down, then the rest: sorts a host's captures together."""
    if not url:
        return ""
    rest = url.split("://", 1)[-1].split("#", 1)[0]
    cut = min((k for k in (rest.find(c) for c in "/?") if k >= 0), default=len(rest))
    return ",".join(reversed(rest[:cut].lower().split("."))) + ")" + (rest[cut:] or "/")


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(id_: int | None, url: str | None, time: str, payload: bytes | None, refers_to: int | None, found: str, size: int | None = None) -> bytes:
    """One record; ``found`` is the payload's digest, ``size`` its length where a revisit comes without it."""
    size = len(payload) if size is None else size
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    revisit = refers_to is not None
    block = http if revisit else http + payload
    target = "".join(c if c.isprintable() and c not in "\r\n" else "%%%02X" % ord(c) for c in url) if url else "urn:none"
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:capture:{'null' if id_ is None else id_}>", f"WARC-Date: {time}", f"WARC-Target-URI: {target}", f"WARC-Payload-Digest: sha1:{found}", "Content-Type: application/http;msgtype=response"]
    if revisit:
        head += [f"WARC-Refers-To: <urn:capture:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head.append(f"Content-Length: {len(block)}")
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(data: bytes) -> dict:
    """Headers and payload of one stored record; raises where lengths or digests disagree."""
    raw = gzip.decompress(data)
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k.lower(): v for k, _, v in (x.partition(": ") for x in lines[1:])}
    size = int(fields["content-length"])
    block, tail = rest[:size], rest[size:]
    if len(block) < size or tail != b"\r\n\r\n":
        raise ValueError("the record's length is wrong")
    http, _, body = block.partition(b"\r\n\r\n")
    length = int(next(x for x in http.decode().split("\r\n") if x.lower().startswith("content-length:")).split(":")[1])
    named = fields["warc-payload-digest"].removeprefix("sha1:")
    number = lambda x: None if x is None or x.endswith(":null>") else int(x.rpartition(":")[2][:-1])
    response = fields["warc-type"] == "response"
    if response and (len(body) != length or digest(body) != named):
        raise ValueError("the payload doesn't match its digest")
    url = fields["warc-target-uri"]
    return {"id": number(fields["warc-record-id"]), "url": None if url == "urn:none" else url, "time": fields["warc-date"], "record_type": fields["warc-type"], "payload_bytes": length, "payload_digest": named, "refers_to": number(fields.get("warc-refers-to")), "payload": body if response else None}


def captured_at(id_: int | None) -> str:
    """A reproducible capture time where the table has none."""
    return (datetime(2024, 1, 1, tzinfo=UTC) + timedelta(seconds=(id_ or 0) % 31_536_000)).strftime("%Y-%m-%dT%H:%M:%SZ")


def with_revisits(pages: DataFrame, id_col: str, url_col: str, payload_col: str) -> DataFrame:
    """(id, url, payload, payload_bytes, sha, refers_to); a revisit may come without its payload.

    Payloads held once stay where they are.  Of repeated ones, rows that can't be
    the response meet the table of repeated digests by id, URL and digest alone;
    what a payload moves for is to be the response, or a filter's rare mistake.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(payload_col).cast("binary"), F.lit(b"")).alias("payload"))
    rows = rows.withColumn("payload_bytes", F.length("payload").cast("long")).withColumn("sha", F.sha1("payload"))
    again = written(rows.groupBy("sha").agg(F.count("*").alias("n"), F.min("id").alias("first")).filter("n > 1").select(F.col("sha").alias("again"), "first"), "warc-digests")
    repeated = among(again.select(F.xxhash64("again").alias("x")))
    response = among(again.select(F.xxhash64("again", "first").alias("x")))
    maybe = repeated(F.xxhash64("sha"))
    # a group without any id has no least one: its rows are responses, hashed as (digest, null)
    met = rows.filter(maybe).withColumn("payload", F.when(response(F.xxhash64("sha", "id")), F.col("payload")))
    met = met.join(again, F.col("sha") == F.col("again"), "left")
    refers_to = F.when(~F.col("id").eqNullSafe(F.col("first")), F.col("first")).alias("refers_to")
    return rows.filter(~maybe).withColumn("refers_to", F.lit(None).cast("long")).unionByName(met.select("id", "url", "payload", "payload_bytes", "sha", refers_to))


def write_archives(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", prefix: str = "crawl", level: int = 1) -> DataFrame:
    """Stored archives: (archive, offset, data), a table in the shared folder."""
    ship_package(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, offset = f"{prefix}-{TaskContext.get().partitionId():06d}.warc.gz", 0
        for batch in batches:
            for k in range(0, batch.num_rows, 128):
                data, at = [], []
                for r in batch.slice(k, 128).to_pylist():
                    found = base64.b32encode(bytes.fromhex(r["sha"])).decode()
                    x = gzip.compress(record(r["id"], r["url"], captured_at(r["id"]), r["payload"], r["refers_to"], found, r["payload_bytes"]), level, mtime=0)
                    data.append(x)
                    at.append(offset)
                    offset += len(x)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(data)), pa.array(at, pa.int64()), pa.array(data, pa.binary())], ["archive", "offset", "data"])

    rows = with_revisits(pages, id_col, url_col, payload_col)
    return written(rows.mapInArrow(run, RECORD), "warc", "none")


def read_archives(archives: DataFrame, with_payload: bool = True) -> DataFrame:
    """Captures parsed from the stored bytes; payload null for revisits, and for all unless ``with_payload``."""
    ship_package(archives.sparkSession)
    names = [x.split()[0] for x in CAPTURE.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = None
        for batch in batches:
            for k in range(0, batch.num_rows, 128):
                rows = []
                for r in batch.slice(k, 128).to_pylist():
                    x = parse(r["data"])
                    rows.append(x | {"url_key": url_key(x["url"]), "archive": r["archive"], "offset": r["offset"], "length": len(r["data"]), "payload": x["payload"] if with_payload else None})
                kinds = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
                schema = schema or pa.schema([(n, kinds[x.split()[1]]) for n, x in zip(names, CAPTURE.split(", "), strict=True)])
                yield pa.RecordBatch.from_pylist(rows, schema)

    return archives.select("archive", "offset", "data").mapInArrow(run, CAPTURE)


class LoserTree:
    """Merges sorted runs; runs may join while merging goes on.

    Leaves hold each run's next key, an inner node the run that lost there, and
    ``winner`` the run that won all: replacing its key replays one path.
    """

    def __init__(self, size: int) -> None:
        self.size = 1 << max(0, size - 1).bit_length()
        self.key: list = [None] * self.size  # None: nothing left
        self.lost = [-1] * self.size
        self.winner = -1

    def _less(self, a: int, b: int) -> bool:
        ka, kb = self.key[a], self.key[b]
        return ka is not None and (kb is None or ka < kb or (ka == kb and a < b))

    def build(self) -> None:
        won = [*([0] * self.size), *range(self.size)]
        for k in range(self.size - 1, 0, -1):
            a, b = won[2 * k], won[2 * k + 1]
            won[k], self.lost[k] = (a, b) if self._less(a, b) else (b, a)
        self.winner = won[1] if self.size > 1 else 0

    def replace(self, key) -> None:
        """The winner's run goes on with this key (None: it has ended)."""
        run = self.winner
        self.key[run] = key
        k = (run + self.size) // 2
        while k:
            if self._less(self.lost[k], run):
                run, self.lost[k] = self.lost[k], run
            k //= 2
        self.winner = run


def merge_blocks(blocks: Iterator[tuple[tuple, Callable[[], list[tuple]]]]) -> Iterator[tuple]:
    """One sorted stream from blocks that come by first key.

    Each item is (first key, opener); a block is opened when its first key isn't
    after the least key at hand, and takes the leaf of one that has ended.
    """
    tree = LoserTree(1)
    tree.build()
    runs: list[Iterator] = [iter(())]
    now: list = [None]
    free = [0]
    coming = next(blocks, None)
    while True:
        best = tree.key[tree.winner]
        while coming is not None and (best is None or coming[0] <= best):
            if not free:  # double the leaves
                old = tree
                tree = LoserTree(2 * old.size)
                tree.key[: old.size] = old.key
                runs += [iter(())] * old.size
                now += [None] * old.size
                free = list(range(old.size, tree.size))[::-1]
            leaf = free.pop()
            runs[leaf] = iter(coming[1]())
            now[leaf] = next(runs[leaf], None)
            tree.key[leaf] = now[leaf][0] if now[leaf] else None
            tree.build()
            best = tree.key[tree.winner]
            coming = next(blocks, None)
        if best is None:
            return
        leaf = tree.winner
        yield now[leaf]
        now[leaf] = next(runs[leaf], None)
        if now[leaf] is None:
            free.append(leaf)
        tree.replace(now[leaf][0] if now[leaf] else None)


def merge_index(captures: DataFrame, ranges: int | None = None, sample_rows: int = 10_000) -> DataFrame:
    """Captures in order of (url_key, time, id, archive, offset) with their global ``position`` from 0.

    Range borders come from a bounded sample of keys and only balance the work.
    """
    spark = captures.sparkSession
    ship_package(spark)
    columns = [c for c in captures.columns if c != "payload"]
    rows = captures.select(*columns)
    key = ["url_key", "time", "id", "archive", "offset"]
    runs = written(rows.sortWithinPartitions(*key), "warc-runs")
    total = runs.count()
    ranges = ranges or max(1, min(20_000, max(spark.sparkContext.defaultParallelism, total // 250_000)))
    seen = runs.select(*key).sample(min(1.0, 2 * sample_rows / max(1, total)), seed=7).limit(4 * sample_rows).toArrow().to_pylist()
    order = lambda r: tuple((r[c] is not None, r[c]) if r[c] is not None else (False,) for c in key)  # noqa: E731  nulls first
    seen = sorted(map(order, seen))
    borders = [seen[k * len(seen) // ranges] for k in range(1, ranges)] if len(seen) >= ranges else []
    schema = rows.schema

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import bisect

        last, at = None, -1
        kept: list[dict] = []

        def packed() -> pa.RecordBatch:
            sink = pa.BufferOutputStream()
            t = pa.RecordBatch.from_pylist(kept, arrow)
            with pa.ipc.new_stream(sink, arrow) as w:
                w.write_batch(t)
            first = kept[0]
            return pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), *(pa.array([first[c]], arrow.field(c).type) for c in key), pa.array([len(kept)]), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["range", *key, "rows", "block"])

        arrow = None
        for batch in batches:
            arrow = arrow or pa.schema([pa.field(f.name, f.type) for f in batch.schema])
            for r in batch.to_pylist():
                mine = order(r)
                where = bisect.bisect_right(borders, mine)
                if kept and (where != at or len(kept) >= BLOCK or mine < last):
                    yield packed()
                    kept.clear()
                at, last = where, mine
                kept.append(r)
        if kept:
            yield packed()

    cut = written(runs.mapInArrow(blocks, "range int, " + ", ".join(f"{c} {schema[c].dataType.simpleString()}" for c in key) + ", rows long, block binary"), "warc-blocks")
    base, before = {}, 0
    for r in cut.groupBy("range").agg(F.sum("rows").alias("n")).orderBy("range").collect():  # as many rows as ranges
        base[r["range"]], before = before, before + r["n"]
    moved = cut.repartitionById(len(borders) + 1, "range").sortWithinPartitions("range", *key)

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        which: list[int] = []

        def incoming() -> Iterator[tuple]:
            for batch in batches:
                for k in range(batch.num_rows):
                    r = batch.slice(k, 1).to_pylist()[0]
                    which.append(r["range"])
                    yield order(r), (lambda data=r["block"]: [(order(x), x) for x in pa.ipc.open_stream(data).read_all().to_pylist()])

        out: list[dict] = []
        position = None
        for _, r in merge_blocks(incoming()):
            position = base[which[0]] if position is None else position + 1
            out.append(r | {"position": position})
            if len(out) == 4096:
                yield pa.RecordBatch.from_pylist(out, result)
                out = []
        if out:
            yield pa.RecordBatch.from_pylist(out, result)

    kinds = {"bigint": pa.int64(), "string": pa.string()}
    result = pa.schema([*(pa.field(f.name, kinds[f.dataType.simpleString()]) for f in schema.fields), pa.field("position", pa.int64())])
    return moved.mapInArrow(merged, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in schema.fields), "position long"]))


def capture_history(index: DataFrame) -> DataFrame:
    """Captures, first and last time of each URL key."""
    return index.groupBy("url_key").agg(F.count("*").alias("captures"), F.min("time").alias("first_time"), F.max("time").alias("last_time"), F.count_if(F.col("record_type") == "revisit").alias("revisits"))


def export_files(archives: DataFrame, folder: str) -> list[str]:
    """Real ``.warc.gz`` files from stored archives, one archive after another through the driver (for local use)."""
    import os

    os.makedirs(folder, exist_ok=True)
    names = []
    for r in archives.orderBy("archive", "offset").toLocalIterator():
        path = os.path.join(folder, r["archive"])
        if path not in names:
            names.append(path)
            open(path, "wb").close()
        with open(path, "ab") as f:
            f.write(r["data"])
    return names
