"""WARC archives of pages, and their capture index merged from locally sorted runs.

Writing: of pages with equal payloads of at least SMALLEST bytes the one with the smallest page_id becomes
a response record, the others revisit records that name it; smaller payloads are always responses. Each
task writes its pages to archives of about ROLL bytes, every record a gzip member of its own, so that
an index entry (archive, offset) opens it directly. Names carry the task's attempt: what a lost attempt
leaves behind is never read.

Reading: a task reads one archive after another and checks every digest. An archive's index entries,
sorted by URL key, time and page_id, are a run, written as a file of small record batches that can be entered
anywhere. The merge is external: a loser tree over k runs holds one batch of each, whatever their lengths, and costs one
comparison a level for each entry. As long as there are more than FAN_IN runs, groups of FAN_IN are merged into
longer ones; the rest is merged range by range of the keys, so that one URL with very many captures spreads. A range's
task finds its place in every run by bisection.

Defined results: a null html is an empty payload; a null url has the key ''; rows that repeat the smallest
page_id of their payload are responses each; a null page_id is never the smallest, its row has none in
the archive either, and its record is named after its place; captures at the same time order by page_id; an empty table gives an empty result; extra columns
are ignored. A page without a capture time gets one from its page_id, a second apart.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Callable, Iterator
from datetime import UTC, datetime, timedelta
from itertools import islice
from urllib.parse import urlsplit

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.llm.common import cut, cut_texts, fresh_dir, slices

SMALLEST = 100
ROLL = 32 << 20
CHUNK = 8192
#: Runs that one task merges, entries of a batch, and entries of a range, about.
FAN_IN, BATCH, RANGE = 1024, 256, 16_384
#: Keys that the driver looks at to cut ranges, at most about.
KEY_SAMPLE = 20_000
EPOCH = datetime(2024, 1, 1, tzinfo=UTC)
SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")
RECORD = "page_id string, url string, url_key string, captured_at string, payload_bytes long, payload_digest string, record_type string, refers_to string, archive string, offset long, length long"


class LoserTree:
    """Merges iterables that are sorted by key. Inner nodes remember the loser of their match; taking the winner
    replays only its path to the root. Ties go to the earlier iterable."""

    def __init__(self, runs: list[Iterator], key: Callable = lambda x: x):
        self.runs, self.key = runs, key
        self.heads = [self._next(i) for i in range(len(runs))]
        self.size = 1 << max(0, (len(runs) - 1).bit_length())
        self.losers = [-1] * self.size
        winners = [i if i < len(runs) else -1 for i in range(self.size)]
        level = self.size
        while level > 1:
            level //= 2
            matched = []
            for k in range(level):
                a, b = winners[2 * k], winners[2 * k + 1]
                win, lose = (a, b) if self._beats(a, b) else (b, a)
                self.losers[level + k] = lose
                matched.append(win)
            winners = matched
        self.winner = winners[0] if runs else -1

    def _next(self, i: int):
        return next(self.runs[i], None)

    def _beats(self, a: int, b: int) -> bool:
        x, y = (self.heads[k] if k >= 0 else None for k in (a, b))
        if x is None or y is None:
            return y is None and (x is not None or a >= 0 > b or a < b)
        x, y = self.key(x), self.key(y)
        return x < y or (x == y and a < b)

    def __iter__(self):
        while self.winner >= 0 and (head := self.heads[self.winner]) is not None:
            yield head
            i = self.winner
            self.heads[i] = self._next(i)
            at = (self.size + i) // 2
            while at >= 1:
                if self.losers[at] >= 0 and self._beats(self.losers[at], i):
                    self.losers[at], i = i, self.losers[at]
                at //= 2
            self.winner = i


def url_key(url: str | None) -> str:
    """Sort-friendly form: host labels reversed, then path and query; no scheme, default port or fragment."""
    if not url:
        return ""
    try:
        parts = urlsplit(url.strip())
        host, port = (parts.hostname or "").lower(), parts.port
    except ValueError:
        return url
    name = ",".join(reversed(host.split("."))) + (f":{port}" if port and port not in (80, 443) else "")
    return f"{name}){parts.path or '/'}" + (f"?{parts.query}" if parts.query else "")


def stamp(page_id: int | None) -> str:
    return (EPOCH + timedelta(seconds=(page_id or 0) % (1 << 31))).strftime("%Y-%m-%dT%H:%M:%SZ")


def record_bytes(name: str, page_id: str | None, url: str, at: str, payload: bytes, digest: str, refers_to: str | None) -> bytes:
    """One record, uncompressed."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    named = lambda x: f"<urn:uuid:{uuid.uuid5(SPACE, x)}>"
    head = [
        "WARC/1.1", f"WARC-Type: {'revisit' if refers_to is not None else 'response'}", f"WARC-Record-ID: {named(name)}", f"WARC-Date: {at}",
        f"WARC-Target-URI: {url}", "Content-Type: application/http; msgtype=response", f"WARC-Payload-Digest: sha256:{digest}", f"Content-Length: {len(block)}",
    ]
    if page_id is not None:
        head.append(f"Page-Id: {page_id}")
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {named(f'page:{refers_to}')}", f"Refers-To-Page: {refers_to}"]
    return "\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + block + b"\r\n\r\n"


def members(data: bytes) -> Iterator[tuple[int, int, bytes]]:
    """(offset, length, content) of the gzip members of an archive."""
    view, at = memoryview(data), 0
    while at < len(data):
        z, end, parts = zlib.decompressobj(31), at, []
        while not z.eof and end < len(data):  # bit by bit, for what a member leaves over is copied
            part = view[end : end + CHUNK]
            parts.append(z.decompress(part))
            end += len(part)
        if not z.eof:
            raise ValueError(f"archive ends within a record at {at}")
        end -= len(z.unused_data)
        yield at, end - at, b"".join(parts)
        at = end


def parsed(content: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of one record."""
    head, _, rest = content.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    fields["HTTP"] = http.decode("latin-1")
    return fields, payload


def _opened(folder: str):
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(folder)
    return system, path


def decided(pages: DataFrame, smallest: int = SMALLEST) -> DataFrame:
    """pages with payload (binary), digest, refers_to (null: a response)."""
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    light = pages.select("page_id", F.sha2(payload, 256).alias("digest"), F.octet_length(payload).alias("n"))
    first = light.where(F.col("n") >= smallest).groupBy("digest").agg(F.min("page_id").alias("first_page"), F.count("*").alias("copies"))
    first = cut(first.where("copies > 1").select(F.col("digest").alias("copied"), "first_page"), "warc-copies")
    rows = pages.select("page_id", "url", payload.alias("payload")).withColumn("digest", F.sha2("payload", 256))
    joined = rows.join(first, F.col("digest") == F.col("copied"), "left")
    refers = F.when(F.col("page_id").isNull() | (F.col("page_id") > F.col("first_page")), F.col("first_page"))
    return joined.select(F.col("page_id").cast("string").alias("page_id"), "url", "payload", "digest", refers.cast("string").alias("refers_to"))


def write_archives(records: DataFrame, folder: str, roll: int = ROLL) -> DataFrame:
    """Write page_id, url, payload, digest, refers_to to archives; return their names and numbers of records."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        task, serial, parts, size = TaskContext.get(), 0, [], 0
        system, path = _opened(folder)
        system.create_dir(path, recursive=True)

        def close() -> pd.DataFrame:
            name = f"{task.partitionId():06d}-{task.taskAttemptId()}-{serial:04d}.warc.gz"
            with system.open_output_stream(f"{path}/{name}", compression=None) as f:
                for p in parts:
                    f.write(p)
            return pd.DataFrame({"archive": [name], "records": [len(parts)]})

        for batch in slices(batches, "payload"):
            for page, url, payload, digest, refers in batch.itertuples(index=False):
                # A header is one line; what would break it is kept percent-encoded.
                shown = (url or "").replace("\r", "%0D").replace("\n", "%0A")
                name = f"page:{page}" if page is not None else f"place:{task.partitionId()}/{task.taskAttemptId()}/{serial}/{len(parts)}"
                raw = record_bytes(name, page, shown, stamp(None if page is None else int(page)), payload, digest, refers)
                z = zlib.compressobj(6, zlib.DEFLATED, 31)
                parts.append(z.compress(raw) + z.flush())
                size += len(parts[-1])
                if size >= roll:
                    yield close()
                    serial, parts, size = serial + 1, [], 0
        if parts:
            yield close()

    return records.mapInPandas(run, "archive string, records long")


COLUMNS = [c.split()[0] for c in RECORD.split(", ")]
KEY = [COLUMNS.index(c) for c in ("url_key", "captured_at", "page_id")]
RUN = "run string, entries long"


def key_of(row: tuple) -> tuple[str, str, int]:
    return row[KEY[0]], row[KEY[1]], int(row[KEY[2]] or -1)


def write_run(system, path: str, rows: Iterator[tuple]) -> int:
    """Write sorted rows as a file of record batches; return their number. One batch is held at a time."""
    import pyarrow as pa

    kinds = {"string": pa.string(), "long": pa.int64()}
    schema, n = pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in RECORD.split(", ")]), 0
    with system.open_output_stream(path) as out, pa.ipc.new_file(out, schema) as file:
        while part := list(islice(rows, BATCH)):
            file.write_batch(pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*part, strict=True), schema, strict=True)], schema=schema))
            n += len(part)
    return n


class Run:
    """A run file, entered at any key."""

    def __init__(self, system, path: str):
        import pyarrow as pa

        self.file = pa.ipc.open_file(system.open_input_file(path))

    def rows(self, batch: int) -> list[tuple]:
        return list(zip(*(c.to_pylist() for c in self.file.get_batch(batch).columns), strict=True))

    def fences(self) -> Iterator[tuple[str, str, int]]:
        """The first key of every batch."""
        for i in range(self.file.num_record_batches):
            yield key_of(next(zip(*(c.slice(0, 1).to_pylist() for c in self.file.get_batch(i).columns), strict=True)))

    def within(self, low: tuple | None = None, high: tuple | None = None) -> Iterator[tuple]:
        """Rows of keys from low up to but not high."""
        a, b = 0, self.file.num_record_batches
        while low is not None and b - a > 1:  # the first key of batch a is below low, or a is 0
            middle = (a + b) // 2
            if key_of(self.rows(middle)[0]) < low:
                a = middle
            else:
                b = middle
        for i in range(a, self.file.num_record_batches):
            for row in self.rows(i):
                key = key_of(row)
                if high is not None and key >= high:
                    return
                if low is None or key >= low:
                    yield row


def read_archives(names: DataFrame, folder: str, runs_folder: str) -> DataFrame:
    """run, entries: the entries of each named archive, sorted, as a file in runs_folder."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        system, path = _opened(folder)
        _, to = _opened(runs_folder)
        system.create_dir(to, recursive=True)
        for batch in batches:
            for name in batch["archive"]:
                with system.open_input_stream(f"{path}/{name}", compression=None) as f:
                    data = f.read()
                rows = []
                for at, used, content in members(data):
                    h, payload = parsed(content)
                    digest = h["WARC-Payload-Digest"].removeprefix("sha256:")
                    if h["WARC-Type"] == "response" and hashlib.sha256(payload).hexdigest() != digest:
                        raise ValueError(f"{name} at {at}: the payload does not match its digest")
                    n = int(h["HTTP"].rpartition("Content-Length: ")[2])
                    url = h["WARC-Target-URI"]
                    rows.append((h.get("Page-Id"), url, url_key(url), h["WARC-Date"], n, digest, h["WARC-Type"], h.get("Refers-To-Page"), name, at, used))
                made = f"{name}-{TaskContext.get().taskAttemptId()}.run"
                yield pd.DataFrame({"run": [made], "entries": [write_run(system, f"{to}/{made}", iter(sorted(rows, key=key_of)))]})

    return names.select("archive").mapInPandas(run, RUN)


def longer_runs(runs: DataFrame, folder: str, fan_in: int = FAN_IN) -> DataFrame:
    """run, entries of runs that hold up to fan_in of the given ones each."""

    def merge(group: pd.DataFrame) -> pd.DataFrame:
        from pyspark import TaskContext

        system, path = _opened(folder)
        names = sorted(group["run"])
        made = f"merged-{TaskContext.get().taskAttemptId()}-{names[0]}"
        tree = LoserTree([Run(system, f"{path}/{x}").within() for x in names], key_of)
        return pd.DataFrame({"run": [made], "entries": [write_run(system, f"{path}/{made}", iter(tree))]})

    numbered = runs.withColumn("group", F.floor((F.row_number().over(W.orderBy("run")) - 1) / fan_in))  # a row an archive
    return numbered.groupBy("group").applyInPandas(merge, RUN)


def ranges(runs: DataFrame, folder: str, entries: int, rows: int = RANGE) -> list[tuple]:
    """Keys that cut all entries into ranges of about as many rows."""
    share = min(1.0, KEY_SAMPLE * BATCH / max(entries, 1))

    def fences(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        system, path = _opened(folder)
        for batch in batches:
            for name in batch["run"]:
                yield pd.DataFrame(list(Run(system, f"{path}/{name}").fences()), columns=["url_key", "captured_at", "page_no"])

    found = runs.select("run").mapInPandas(fences, "url_key string, captured_at string, page_no long")
    keys = sorted(tuple(r) for r in (found if share == 1.0 else found.sample(share, seed=1)).collect())  # about KEY_SAMPLE rows
    parts = max(1, -(-entries // rows))
    return sorted({keys[len(keys) * i // parts] for i in range(1, parts)}) if keys else []


def merged_index(runs: DataFrame, folder: str, fan_in: int = FAN_IN, rows: int = RANGE) -> DataFrame:
    """The capture history: all entries by URL key, time and page. Partitions are consecutive ranges."""
    spark = runs.sparkSession
    number, entries = runs.agg(F.count("*"), F.sum("entries")).first()
    while number > fan_in:
        runs = cut(longer_runs(runs, folder, fan_in), "warc-runs")
        number = runs.count()
    names = sorted(r["run"] for r in runs.select("run").collect())  # fan_in names at most
    splits = ranges(runs, folder, entries or 0, rows)
    bounds = list(zip([None, *splits], [*splits, None], strict=True))

    def merge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        system, path = _opened(folder)
        for batch in batches:
            for i in batch["id"]:
                tree = iter(LoserTree([Run(system, f"{path}/{x}").within(*bounds[i]) for x in names], key_of))
                while part := list(islice(tree, 4096)):
                    yield pd.DataFrame(part, columns=COLUMNS)

    return spark.range(0, len(bounds), 1, len(bounds)).mapInPandas(merge, RECORD)


def archived(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """Write pages as archives, read them back, and return their capture history."""
    spark: SparkSession = pages.sparkSession
    folder, runs_folder = folder or fresh_dir(spark, "warc"), fresh_dir(spark, "warc-runs")
    names = cut_texts(write_archives(decided(pages), folder), "warc-names")
    names = names.repartition(max(2, min(10_000, names.count())))
    return merged_index(cut(read_archives(names, folder, runs_folder), "warc-runs"), runs_folder)


def op8_warc(pages: DataFrame) -> DataFrame:
    return archived(pages).select(
        F.col("page_id").cast("long").alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast("long").alias("refers_to"), "url_key", "captured_at"
    )


SQL = """
WITH p AS (SELECT page_id, url, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
f AS (SELECT payload_digest, min(page_id) AS first_page FROM p WHERE payload_bytes >= 100 GROUP BY payload_digest),
k AS (SELECT p.*, first_page, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path,
        regexp_extract(url, '[?]([^#]*)', 1) AS query FROM p LEFT JOIN f USING (payload_digest))
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id > first_page THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN page_id > first_page THEN first_page END AS refers_to,
       array_to_string(list_reverse(string_split(lower(host), '.')), ',') || ')' || CASE WHEN path = '' THEN '/' ELSE path END || CASE WHEN query <> '' THEN '?' || query ELSE '' END AS url_key,
       strftime(timestamp '2024-01-01' + page_id * interval 1 second, '%Y-%m-%dT%H:%M:%SZ') AS captured_at FROM k
"""
