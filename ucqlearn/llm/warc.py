"""WARC archives, and capture histories by an external merge of their indexes.

Tasks write gzip archives into the shared folder, one member a record, and roll over at a size. The archives are read back
record by record; each yields an index run sorted by (URL key, timestamp, page). Runs are cut into key ranges, and each range
is merged from its runs by a loser tree, so that the ranges, in order, hold all captures in global order.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from datetime import datetime, timedelta, timezone
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, row_count, texts

PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"  # fixed value
EPOCH = datetime(2024, 1, 1, tzinfo=timezone.utc)


def url_key(url: str) -> str:
    """Host labels reversed, without www and port, then path and query in lower case."""
    try:
        parts = urlsplit(url.strip().lower())
        host = re.sub(r"^www\d*\.", "", parts.hostname or "")
    except ValueError:
        return url.strip().lower()
    return f"{','.join(reversed(host.split('.')))}){parts.path or '/'}{'?' + parts.query if parts.query else ''}"


def capture_time(page_id: int | None) -> datetime:
    """Pages carry no time; a second for each page number, so that a page's time is always the same."""
    return EPOCH + timedelta(seconds=(page_id or 0) % (1 << 31))


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page {page_id}')}>"


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def build_record(page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    """A response, or a revisit (HTTP head only) if ``refers_to`` names the page of the response."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    clean = re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url or "")
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {capture_time(page_id):%Y-%m-%dT%H:%M:%SZ}", f"WARC-Target-URI: {clean}", f"WARC-Payload-Digest: sha1:{digest}"]
    if refers_to is not None:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(refers_to)}", f"WARC-Refers-To-Date: {capture_time(refers_to):%Y-%m-%dT%H:%M:%SZ}", f"X-Refers-To-Page: {refers_to}"]
    head += [f"X-Page: {'' if page_id is None else page_id}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def members(content: bytes):
    """(offset, length, bytes) of each gzip member. Slices are fed, so that no member copies the rest of the archive."""
    view, at = memoryview(content), 0
    while at < len(content):
        start, d, out = at, zlib.decompressobj(31), []
        while not d.eof and at < len(content):
            part = view[at : at + 65536]
            out.append(d.decompress(part))
            at += len(part) - len(d.unused_data)
        if not d.eof:
            raise ValueError("the archive ends inside a record")
        yield start, at - start, b"".join(out)


def parse_record(data: bytes) -> dict:
    head, _, rest = data.partition(b"\r\n\r\n")
    version, *lines = head.decode().split("\r\n")
    fields = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines)
    block = rest[: int(fields["Content-Length"])]
    if version != "WARC/1.1" or rest[len(block) :] != b"\r\n\r\n":
        raise ValueError("not a whole WARC record")
    http, _, payload = block.partition(b"\r\n\r\n")
    stated = int(re.search(rb"\r\nContent-Length: (\d+)", http)[1])
    digest = fields["WARC-Payload-Digest"].removeprefix("sha1:")
    if fields["WARC-Type"] == "response" and (len(payload) != stated or payload_digest(payload) != digest):
        raise ValueError("the payload is not the one that was written")
    number = lambda x: int(x) if x else None
    when = fields["WARC-Date"]
    return {"page_id": number(fields["X-Page"]), "url": fields["WARC-Target-URI"], "timestamp": re.sub(r"\D", "", when), "payload": payload, "payload_bytes": stated, "payload_digest": digest, "record_type": fields["WARC-Type"], "refers_to": number(fields.get("X-Refers-To-Page"))}


def _writer(folder: str, most_bytes: int, level: int):
    def run(batches):
        from pyarrow import fs

        system, base = fs.FileSystem.from_uri(folder)
        system.create_dir(base)
        context = TaskContext.get()
        part, attempt = (context.partitionId(), context.taskAttemptId()) if context else (0, 0)
        held, size, done = [], 0, []

        def flush():
            # a repeated task writes the same archive again; not every store renames onto a name that is there
            name = f"{base}/part-{part:06d}-{len(done):04d}.warc.gz"
            with system.open_output_stream(f"{base}/.tmp-{part}-{attempt}", compression=None) as out:
                for x in held:
                    out.write(x)
            if system.get_file_info(name).type != fs.FileType.NotFound:
                system.delete_file(name)
            system.move(f"{base}/.tmp-{part}-{attempt}", name)
            done.append(name)

        for batch in batches:
            ids, urls, refers = (batch.column(i).to_pylist() for i in (0, 1, 3))
            for i, url, payload, ref in zip(ids, urls, texts(batch.column(2)), refers):
                d = zlib.compressobj(level, zlib.DEFLATED, 31)
                held.append(d.compress(build_record(i, url, payload, payload_digest(payload), ref)) + d.flush())
                size += len(held[-1])
                if size >= most_bytes:
                    flush()
                    held, size = [], 0
        if held:
            flush()
        yield pa.RecordBatch.from_arrays([pa.array(done, pa.string())], names=["archive"])

    return run


def write_archives(pages: DataFrame, folder: str, most_bytes: int = 8 << 20, level: int = 6) -> int:
    """Writes page_id, url, html, refers_to as archives of about ``most_bytes``; returns how many. Rows are sorted in
    each partition, so that a repeated task writes the same bytes."""
    rows = pages.select("page_id", "url", "html", "refers_to").sortWithinPartitions("page_id", "url")
    return row_count(rows.mapInArrow(_writer(folder, most_bytes, level), "archive string"))


LISTED = 1 << 19  # most repeated payloads that are broadcast


def resolve_revisits(pages: DataFrame, least_bytes: int = 0, work: Workspace | None = None) -> DataFrame:
    """``pages`` with refers_to: for payloads of ``least_bytes`` at least, the largest page_id with an equal payload
    (null for that page itself). Payloads are compared by SHA-1 and size, summed up before any shuffle; pages themselves are
    shuffled only where more payloads repeat than can be broadcast."""
    work = work or Workspace(pages.sparkSession, "warc")
    html = F.coalesce("html", F.lit(""))
    keyed = pages.select("page_id", F.sha1(html.cast("binary")).alias("_d"), F.octet_length(html).alias("_n"))
    heads = keyed.where(F.col("_n") >= least_bytes).groupBy("_d", "_n").agg(F.max("page_id").alias("_head"), F.count(F.lit(1)).alias("_k")).where("_k > 1 and _head is not null")
    heads = work.put(heads.select("_d", "_n", "_head"), "heads")
    rows = pages.select("page_id", "url", "html").withColumn("_d", F.sha1(html.cast("binary"))).withColumn("_n", F.octet_length(html))
    joined = rows.join(F.broadcast(heads) if row_count(heads) <= LISTED else heads, ["_d", "_n"], "left")
    return joined.select("page_id", "url", "html", F.when(~F.col("_head").eqNullSafe(F.col("page_id")), F.col("_head")).alias("refers_to"))


RUN = "run string, at long, urlkey string, timestamp string, page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, offset long, length long"


def _reader(batches):
    for batch in batches:
        for path, content in zip(batch.column(0).to_pylist(), batch.column(1)):
            rows = []
            for offset, length, data in members(content.as_py()):
                r = parse_record(data)
                rows.append((url_key(r["url"]), r["timestamp"], r["page_id"], r["url"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"], offset, length))
            rows.sort(key=_order)
            name = path.rsplit("/", 1)[-1]
            yield pa.RecordBatch.from_pylist([dict(zip(_RUN_NAMES, (name, i, *r))) for i, r in enumerate(rows)], schema=_RUN_SCHEMA)


_RUN_NAMES = [x.split()[0] for x in RUN.split(", ")]
_RUN_SCHEMA = pa.schema([(n, pa.string() if t == "string" else pa.int64()) for n, t in (x.split() for x in RUN.split(", "))])


def _order(r):
    return r[0], r[1], -1 if r[2] is None else r[2], r[8]


def index_runs(spark, folder: str) -> DataFrame:
    """Reads all archives back: a sorted run for each, in rows of RUN."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*.warc.gz").load(folder)
    return files.select("path", "content").mapInArrow(_reader, RUN)


class LoserTree:
    """Merges sorted iterators: an inner node keeps the loser of its match, so that each item costs one path of matches."""

    def __init__(self, runs, key):
        self.key, self.runs = key, [iter(r) for r in runs]
        self.heads = [self._next(i) for i in range(len(self.runs))]
        self.k = max(1, len(self.runs))
        self.losers = [None] * self.k
        self.winner = self._build()

    def _next(self, i):
        item = next(self.runs[i], None)
        return None if item is None else (self.key(item), i, item)

    def _beats(self, a, b) -> bool:
        x, y = self.heads[a], self.heads[b]
        return y is None or (x is not None and x[:2] < y[:2])

    def _build(self):
        if not self.runs:
            return None
        nodes = [None] * self.k + list(range(self.k))
        for n in range(self.k - 1, 0, -1):
            a, b = nodes[2 * n], nodes[2 * n + 1]
            nodes[n], self.losers[n] = (a, b) if self._beats(a, b) else (b, a)
        return nodes[1] if self.k > 1 else 0

    def __iter__(self):
        while self.winner is not None and self.heads[self.winner] is not None:
            w = self.winner
            yield self.heads[w][2]
            self.heads[w] = self._next(w)
            n = (w + self.k) // 2
            while n:
                if self._beats(self.losers[n], w):
                    w, self.losers[n] = self.losers[n], w
                n //= 2
            self.winner = w


def _merger(batches):
    context = TaskContext.get()
    place = (context.partitionId() if context else 0) << 33
    runs: dict[str, list] = {}
    for batch in batches:  # sorted by (run, at): each run's share of the range is one stretch
        for r in zip(*[c.to_pylist() for c in batch.columns]):
            runs.setdefault(r[0], []).append(r)
    out = []
    for i, r in enumerate(LoserTree(runs.values(), lambda r: _order(r[2:]))):
        out.append((*r, place + i))
        if len(out) == 10_000:
            yield _merged(out)
            out = []
    yield _merged(out)


def _merged(rows):
    columns = list(zip(*rows)) if rows else [[]] * (len(_RUN_NAMES) + 1)
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, [*[f.type for f in _RUN_SCHEMA], pa.int64()])], names=[*_RUN_NAMES, "history_order"])


def merge_runs(runs: DataFrame, each: int = 100_000) -> DataFrame:
    """All rows of ``runs`` with history_order (long), which rises with (urlkey, timestamp, page_id) over the whole result.
    A key range has about ``each`` rows; a URL with more captures is spread over several ranges."""
    parts = max(1, -(-row_count(runs) // each))
    ranged = runs.repartitionByRange(parts, "urlkey", "timestamp", "page_id", "offset") if parts > 1 else runs.coalesce(1)
    return ranged.sortWithinPartitions("run", "at").mapInArrow(_merger, RUN + ", history_order long")


def numbered(merged: DataFrame) -> DataFrame:
    """``merged`` with a history_order from 0 without gaps. The sizes of the key ranges are summed up, one row a range."""
    from pyspark.sql import Window

    part = F.shiftright("history_order", 33)
    sizes = merged.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sizes.select("part", before.alias("start"))
    place = F.col("start") + F.col("history_order").bitwiseAND(F.lit((1 << 33) - 1))
    return merged.withColumn("part", part).join(F.broadcast(starts), "part").withColumn("history_order", place.cast("long")).drop("part", "start")


def capture_histories(spark, pages: DataFrame, least_bytes: int = 0, folder: str | None = None) -> DataFrame:
    """Archives ``pages`` (page_id, url, html), reads the archives back and returns their merged index, a row for each page.

    Null html is an empty payload and null url an empty URL. Of equal payloads the largest page_id is the response; rows
    that share that page_id are all responses, and rows without page_id revisit it. An empty table writes no archive and
    gives no row. Other columns are ignored. history_order numbers all captures by URL key, timestamp and page.
    """
    work = Workspace(spark, "warc")
    folder = folder or work.path("archives")
    if not write_archives(resolve_revisits(pages, least_bytes, work), folder):
        return spark.createDataFrame([], RUN + ", history_order long")
    runs = work.put(index_runs(spark, folder), "runs")
    return numbered(work.put(merge_runs(runs), "merged"))
