"""WARC archives: records written by Spark's text sink, read back, and indexed by an external merge.

A record is a text line whose separator is the blank lines that end a record, so the sink writes archives as they are.
Of equal payloads of at least 100 bytes the one of the smallest page_id is stored as a response and the others as
revisits that refer to it. Readers parse an archive by its content lengths.

The index is an external merge: each archive yields a capture run sorted by URL key and time, which is written to the
shared folder. Runs that a task reads are merged by a tree of losers into one, which is cut at the bounds of the ranges
into blocks; the blocks of a range, sorted each, meet in one task and are merged by a tree of losers again. Nothing is
sorted twice. The bounds come from a hash-drawn sample of the captures and decide the sizes of ranges alone.

Null html is an empty payload; a null url has an empty key. Equal URLs and times keep the order of page_id; repeated rows
stay. An empty table makes no archive and no rows. page_id must be unique for revisits to name one record. Extra columns do
not matter. Archives are bounded by records and by bytes, so that the longest page may be as long as a string can be.
"""

from __future__ import annotations

import bisect
import hashlib
import re
from collections.abc import Callable, Iterator
from datetime import datetime

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine.llm.common import cut, encoded

LEAST_BYTES = 100
RECORDS_PER_FILE = 2_000
#: Bytes of an archive, unless one record alone has more; and of a record's headers without its URL.
ARCHIVE_BYTES, HEAD_BYTES = 32_000_000, 1_000
#: Captures that a task merges at once, of a range on average, and of the sample for the bounds of each range.
RUN_ROWS, RANGE_ROWS, SAMPLED = 200_000, 200_000, 200
END = "\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _uuid(column):
    h = F.md5(F.concat(F.lit("page:"), column.cast("string")))
    return F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *(F.substring(h, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12)))), F.lit(">"))


def records(pages: DataFrame, ts=None) -> DataFrame:
    """page_id, url, ts, html, payload_bytes, payload_digest, refers_to (null for responses).

    ts: the time of capture, a column expression; left out, seconds after an epoch by page_id."""
    ts = F.timestamp_seconds(F.lit(1_700_000_000) + F.col("page_id")) if ts is None else ts
    html = F.coalesce("html", F.lit(""))
    rows = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), ts.alias("ts"), html.alias("html"), F.octet_length(html).cast("long").alias("payload_bytes"), F.sha2(html, 256).alias("payload_digest"))
    firsts = rows.where(F.col("payload_bytes") >= LEAST_BYTES).groupBy("payload_digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1")
    found = rows.join(cut(firsts.select("payload_digest", "first")), "payload_digest", "left")
    return found.withColumn("refers_to", F.when(F.col("first") < F.col("page_id"), F.col("first"))).drop("first")


def record_text(rows: DataFrame) -> DataFrame:
    """page_id and the record as text, without the blank lines that end it."""
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("payload_bytes").cast("string"), F.lit(END))
    block = F.concat(http, F.when(F.col("refers_to").isNull(), F.col("html")).otherwise(""))
    uri = F.regexp_replace(F.col("url"), r"[\r\n]", "")
    head = F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: "), F.when(F.col("refers_to").isNull(), "response").otherwise("revisit"),
        F.lit("\r\nWARC-Record-ID: "), _uuid(F.col("page_id")),
        F.lit("\r\nWARC-Date: "), F.date_format("ts", "yyyy-MM-dd'T'HH:mm:ss'Z'"),
        F.lit("\r\nWARC-Target-URI: "), uri,
        F.lit("\r\nWARC-Payload-Digest: sha256:"), F.col("payload_digest"),
        F.lit("\r\nX-Page-Id: "), F.col("page_id").cast("string"),
        F.when(F.col("refers_to").isNull(), "").otherwise(F.concat(F.lit(f"\r\nWARC-Profile: {PROFILE}\r\nWARC-Refers-To: "), _uuid(F.col("refers_to")), F.lit("\r\nX-Refers-To-Page: "), F.col("refers_to").cast("string"))),
        F.lit("\r\nContent-Type: application/http; msgtype=response\r\nContent-Length: "), F.octet_length(block).cast("string"), F.lit(END),
    )
    return rows.select(F.concat(head, block).alias("value"))


def records_per_file(pages: DataFrame) -> int:
    """As many records as fit ARCHIVE_BYTES whatever their sizes."""
    longest = pages.agg(F.max(F.coalesce(F.octet_length("html"), F.lit(0)) + F.coalesce(F.octet_length("url"), F.lit(0)))).first()[0] or 0
    return max(1, min(RECORDS_PER_FILE, ARCHIVE_BYTES // (longest + HEAD_BYTES)))


def write_archives(rows: DataFrame, path: str, compression: str = "none") -> None:
    """rows: as records gives them."""
    record_text(rows).write.option("lineSep", END).option("compression", compression).option("maxRecordsPerFile", records_per_file(rows)).text(path)


def parse(content: bytes) -> Iterator[tuple[dict[str, str], bytes, bytes]]:
    """(headers, HTTP head, payload) of each record of an archive."""
    at = 0
    while at < len(content):
        end = content.index(b"\r\n\r\n", at)
        version, *lines = content[at:end].decode("utf-8", "surrogatepass").split("\r\n")
        if not version.startswith("WARC/"):
            raise ValueError(f"no record at byte {at}")
        headers = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines)
        start, size = end + 4, int(headers["Content-Length"])
        http, _, payload = content[start : start + size].partition(b"\r\n\r\n")
        yield headers, http, payload
        if content[start + size : start + size + 4] != b"\r\n\r\n":
            raise ValueError(f"the record at byte {at} does not end where its length says")
        at = start + size + 4


def url_key(url: str) -> str:
    """Host labels reversed and joined by commas, then path and query, in lower case: keys of a site sort together."""
    m = re.match(r"(?:[a-z][a-z0-9+.-]*://)?(?:[^/@]*@)?([^/?#]*)([^#]*)", url.lower())
    host = m[1].removeprefix("www.").split(":")[0] if m else ""
    return ",".join(reversed(host.split("."))) + ")" + ((m[2] if m else "") or "/")


CAPTURE = "url_key string, ts long, page_id long, run string, payload_bytes long, payload_digest string, stored_bytes long, stored_digest string, record_type string, refers_to long"


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for path, content in zip(batch.column(0), batch.column(1), strict=True):
            run, rows = path.as_py(), []
            for headers, http, payload in parse(content.as_py()):
                at = datetime.fromisoformat(headers["WARC-Date"].replace("Z", "+00:00"))
                length = int(re.search(rb"Content-Length: (\d+)", http)[1])
                refers = headers.get("X-Refers-To-Page")
                rows.append((url_key(headers["WARC-Target-URI"]), int(at.timestamp()), int(headers["X-Page-Id"]), run, length, headers["WARC-Payload-Digest"].removeprefix("sha256:"), len(payload), hashlib.sha256(payload).hexdigest(), headers["WARC-Type"], int(refers) if refers else None))
            rows.sort(key=lambda r: (encoded(r[0]), r[1], r[2]))
            kinds = [pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], [f.split()[0] for f in CAPTURE.split(", ")])


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """Captures of the archives in path; each file gives a sorted run."""
    try:
        files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path)
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], CAPTURE)
    return files.select("path", "content").mapInArrow(_runs, CAPTURE)


class LoserTree:
    """Merges sorted iterators: each inner node keeps the loser of its match, and a new head replays one path."""

    def __init__(self, runs: list[Iterator], key: Callable) -> None:
        self.runs, self.key = runs, key
        self.heads: list = [None] * len(runs)
        self.keys: list = [None] * len(runs)
        for i in range(len(runs)):
            self._pull(i)
        size = len(runs)
        winners = [*([None] * size), *range(size)]
        self.losers: list = [None] * size
        for node in range(size - 1, 0, -1):
            a, b = winners[2 * node], winners[2 * node + 1]
            winners[node], self.losers[node] = (a, b) if self._less(a, b) else (b, a)
        self.winner = winners[1] if size > 1 else 0

    def _pull(self, i: int) -> None:
        self.heads[i] = next(self.runs[i], None)
        self.keys[i] = None if self.heads[i] is None else (self.key(self.heads[i]), i)

    def _less(self, a: int, b: int) -> bool:
        return self.keys[b] is None or self.keys[a] is not None and self.keys[a] < self.keys[b]

    def __iter__(self) -> Iterator:
        size = len(self.runs)
        while size and self.heads[self.winner] is not None:
            at = self.winner
            yield self.heads[at]
            self._pull(at)
            node = (at + size) // 2
            while node:
                if self._less(self.losers[node], at):
                    at, self.losers[node] = self.losers[node], at
                node //= 2
            self.winner = at


def _keys(rows: pa.Table) -> list[tuple]:
    return list(zip(map(encoded, rows.column("url_key").to_pylist()), rows.column("ts").to_pylist(), rows.column("page_id").to_pylist(), strict=True))


def _merged(runs: list[pa.Table]) -> tuple[pa.Table, list[tuple]]:
    """Sorted tables as one, and its keys."""
    whole, keys = pa.concat_tables(runs), [k for r in runs for k in _keys(r)]
    if len(runs) == 1:
        return whole, keys
    ends = [0]
    for r in runs:
        ends.append(ends[-1] + r.num_rows)
    order = list(LoserTree([iter(range(a, b)) for a, b in zip(ends, ends[1:], strict=False)], keys.__getitem__))
    return whole.combine_chunks().take(pa.array(order, pa.int64())), [keys[i] for i in order]


def _blocks(bounds: list[tuple]):
    """Of captures in runs: blocks (range, rows), each sorted and within one range."""

    def given(batches: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = pa.Table.from_batches(batches)
        names = whole.column("run").to_pylist()
        cuts = [0, *(i for i in range(1, len(names)) if names[i] != names[i - 1]), len(names)]
        rows, keys = _merged([whole.slice(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)])
        rows, at = rows.combine_chunks(), 0
        while at < len(keys):
            part = bisect.bisect_right(bounds, keys[at])
            end = bisect.bisect_left(keys, bounds[part], at) if part < len(bounds) else len(keys)
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rows.schema) as out:
                out.write_table(rows.slice(at, end - at))
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["part", "block"])
            at = end

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                n += batch.num_rows
            if n >= RUN_ROWS:
                yield from given(held)
                held, n = [], 0
        if held:
            yield from given(held)

    return run


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The blocks of one range as rows in order."""
    runs = [pa.ipc.open_stream(block.as_buffer()).read_all() for batch in batches for block in batch.column(1)]
    if runs:
        yield from _merged(runs)[0].to_batches(max_chunksize=10_000)


def merged_index(captures: DataFrame, ranges: int | None = None) -> DataFrame:
    """captures in the global order of URL key, time and page_id: ranges in the order of partitions, runs merged in each."""
    spark = captures.sparkSession
    runs = cut(captures)
    n = runs.count()
    ranges = ranges or max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-n // RANGE_ROWS))
    share = min(1.0, SAMPLED * ranges / max(1, n))
    drawn = runs.where(F.pmod(F.xxhash64("page_id", F.lit("bounds")), F.lit(1_000_000)) < round(share * 1_000_000))
    sample = sorted((encoded(r.url_key), r.ts, r.page_id) for r in drawn.select("url_key", "ts", "page_id").toLocalIterator())
    bounds = sorted({sample[len(sample) * i // ranges] for i in range(1, ranges)}) if sample else []
    blocks = runs.mapInArrow(_blocks(bounds), "part int, block binary").repartitionById(len(bounds) + 1, F.col("part"))
    return blocks.mapInArrow(_merge, CAPTURE)


def archive(pages: DataFrame, path: str) -> DataFrame:
    """Write pages as archives under path, read them back, and return the merged index."""
    write_archives(records(pages), path)
    return merged_index(read_archives(pages.sparkSession, path))
