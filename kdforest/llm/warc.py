"""Web archives: a writer on Spark's text sink, and a Python data source that reads them back.

A record is text in UTF-8 whose end mark (two line breaks) is the text sink's line separator. Archives are written to
any store that Spark can write, plain or in gzip; they are read through pyarrow's file systems (local, hdfs, s3, gs).
The data source plans one partition per archive file, reads a record's
headers first and skips its payload undecoded if the record is filtered out or no payload column is asked for.
Filters on header columns are pushed down.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterable, Iterator
from datetime import UTC, datetime

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition, IsNotNull

from kdforest.llm.common import maybe_broadcast, scratch_path, table

END = "\r\n\r\n"
#: Payloads from this size on are stored once.
LEAST_BYTES = 100
SALTS = 32
SCHEMA = "page_id long, url string, record_type string, refers_to long, payload_digest string, payload_bytes long, computed_digest string, payload string"
HEADER_COLUMNS = {"page_id": "WARC-Page-ID", "url": "WARC-Target-URI", "record_type": "WARC-Type", "refers_to": "WARC-Refers-To-Page-ID", "payload_digest": "WARC-Payload-Digest", "payload_bytes": "WARC-Payload-Length"}


def deduplicated(pages: DataFrame) -> DataFrame:
    """``pages`` (page_id, url, html) with payload, digest, payload_bytes and refers_to, first_url (null: stored in full).

    Of rows with equal payloads of at least 100 bytes that with the smallest page_id is stored; rows that share
    this page_id and payload are all stored. A payload that no row with an id has is stored in each row.
    """
    slim = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce("html", F.lit("")).alias("payload"))
    marked = slim.select("*", F.sha2(F.col("payload").cast("binary"), 256).alias("digest"), F.octet_length("payload").cast("long").alias("payload_bytes"))
    same = marked.where(F.col("payload_bytes") >= LEAST_BYTES).groupBy("digest").agg(F.min(F.when(F.col("page_id").isNotNull(), F.struct("page_id", "url"))).alias("f"), F.count("*").alias("n")).where("n > 1").select("digest", F.col("f.page_id").alias("first"), F.col("f.url").alias("first_url"))
    salted = same.select("digest", "first", "first_url", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))  # copies of one payload may be a third of all rows
    salt = F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")
    found = marked.withColumn("salt", salt).join(maybe_broadcast(salted), ["digest", "salt"], "left")
    return found.withColumn("refers_to", F.when(F.col("page_id") != F.col("first"), F.col("first"))).drop("salt", "first")


def record_id(page_id: Column, url: Column, digest: Column) -> Column:
    return F.concat(F.lit("<urn:sha256:"), F.sha2(F.concat_ws("|", F.coalesce(page_id.cast("string"), F.lit("")), url, digest), 256), F.lit(">"))


def records(marked: DataFrame, date: str) -> DataFrame:
    """The text of each record without its end mark (column value); ``date`` is that of all records."""
    quoted = F.to_json(F.struct(F.col("url").alias("u")))  # line breaks in an address can't break a header
    revisit = F.col("refers_to").isNotNull()
    block = F.when(revisit, F.lit("")).otherwise(F.col("payload"))
    id_text = F.coalesce(F.col("page_id").cast("string"), F.lit(""))
    head = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.when(revisit, "revisit").otherwise("response")),
        F.concat(F.lit("WARC-Record-ID: "), record_id(F.col("page_id"), F.col("url"), F.col("digest"))),
        F.lit(f"WARC-Date: {date}"),
        F.concat(F.lit("WARC-Page-ID: "), id_text),
        F.concat(F.lit("WARC-Target-URI: "), quoted),
        F.concat(F.lit("WARC-Payload-Digest: sha256:"), F.col("digest")),
        F.concat(F.lit("WARC-Payload-Length: "), F.col("payload_bytes").cast("string")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), record_id(F.col("refers_to"), F.col("first_url"), F.col("digest")))),
        F.when(revisit, F.lit(f"WARC-Refers-To-Date: {date}")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To-Page-ID: "), F.col("refers_to").cast("string"))),
        F.when(revisit, F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        F.lit("Content-Type: text/html; charset=utf-8"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    return marked.select(F.concat(F.concat_ws("\r\n", *head), F.lit(END), block).alias("value"))


def write_warc(pages: DataFrame, path: str, date: str | None = None, compression: str | None = None) -> None:
    """Archives of ``pages`` (page_id, url, html) in ``path``; an empty table gives a folder without records.

    A null page is an empty payload, a null address a null one in its header, a null id an empty header; all are records.
    Columns besides the three are ignored. ``date`` defaults to now (UTC), ``compression`` may be "gzip".
    """
    date = date or datetime.now(UTC).strftime("%Y-%m-%dT%H:%M:%SZ")
    sink = records(deduplicated(pages), date).write.option("lineSep", END)
    (sink.option("compression", compression) if compression else sink).text(path)


def _cast(name: str, raw: str | None) -> object:
    if raw is None or raw == "":
        return None
    if name in ("page_id", "refers_to", "payload_bytes"):
        return int(raw)
    if name == "url":
        return json.loads(raw).get("u")
    return raw.removeprefix("sha256:") if name == "payload_digest" else raw


def opened(path: str) -> str:
    """The address by which pyarrow knows a store that Spark calls s3a."""
    return "s3" + path[3:] if path.startswith(("s3a:", "s3n:")) else path


class WarcPartition(InputPartition):
    def __init__(self, path: str, size: int):
        self.path, self.size = path, size


class WarcReader(DataSourceReader):
    def __init__(self, path: str, columns: list[str]):
        self.path, self.columns, self.filters = path, columns, []

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            known = isinstance(f, (EqualTo, In, IsNotNull)) and len(f.attribute) == 1 and f.attribute[0] in HEADER_COLUMNS
            if known:
                name = f.attribute[0]
                self.filters.append((name, "any" if isinstance(f, IsNotNull) else "in", None if isinstance(f, IsNotNull) else {f.value} if isinstance(f, EqualTo) else set(f.value)))
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(opened(self.path))
        infos = store.get_file_info(fs.FileSelector(root, recursive=True))
        files = [i for i in infos if i.is_file and i.size and not i.base_name.startswith(("_", "."))]
        return [WarcPartition(i.path, i.size) for i in sorted(files, key=lambda i: i.path)] or [WarcPartition("", 0)]

    def wanted(self, head: dict[str, object]) -> bool:
        return all(head[n] is not None and (kind == "any" or head[n] in values) for n, kind, values in self.filters)

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from pyarrow import fs

        if not partition.size:
            return
        store = fs.FileSystem.from_uri(opened(self.path))[0]
        packed = partition.path.endswith(".gz")
        with store.open_input_stream(partition.path, compression="gzip") if packed else store.open_input_file(partition.path) as raw:
            stream = Buffered(raw, seeks=not packed)
            while lines := stream.head():
                fields = dict(x.split(": ", 1) for x in lines[1:] if ": " in x)
                length = int(fields["Content-Length"])
                head = {n: _cast(n, fields.get(h)) for n, h in HEADER_COLUMNS.items()}
                body = None
                if self.wanted(head) and {"payload", "computed_digest"} & set(self.columns) and head["record_type"] == "response":
                    body = stream.take(length)
                else:
                    stream.skip(length)
                stream.skip(len(END))
                if self.wanted(head):
                    head["computed_digest"] = None if body is None else hashlib.sha256(body).hexdigest()
                    head["payload"] = body.decode() if body is not None and "payload" in self.columns else None
                    yield tuple(head[c] for c in self.columns)


class Buffered:
    """Sequential reading with cheap skips."""

    def __init__(self, raw, block: int = 1 << 20, seeks: bool = True):
        self.raw, self.block, self.seeks, self.held, self.at = raw, block, seeks, b"", 0

    def more(self) -> bool:
        got = self.raw.read(self.block)
        self.held, self.at = self.held[self.at :] + got, 0
        return bool(got)

    def head(self) -> list[str]:
        mark = END.encode()
        while (end := self.held.find(mark, self.at)) < 0:
            if not self.more():
                return []
        text, self.at = self.held[self.at : end].decode(), end + len(mark)
        return text.split("\r\n")

    def take(self, n: int) -> bytes:
        parts, need = [self.held[self.at : self.at + n]], n
        need -= len(parts[0])
        self.at += len(parts[0])
        while need:
            parts.append(self.raw.read(need))
            if not parts[-1]:
                raise OSError("a record is cut off")
            need -= len(parts[-1])
        return b"".join(parts)

    def skip(self, n: int) -> None:
        held = min(n, len(self.held) - self.at)
        self.at += held
        left = n - held
        if left and self.seeks:
            self.raw.seek(self.raw.tell() + left)
            return
        while left:
            got = len(self.raw.read(min(left, self.block)))
            if not got:
                raise OSError("a record is cut off")
            left -= got


class WarcDataSource(DataSource):
    """``spark.read.format("warc").option("columns", "page_id,record_type").load(path)``; columns default to all."""

    @classmethod
    def name(cls) -> str:
        return "warc"

    def wanted(self) -> list[str]:
        every = [c.split()[0] for c in SCHEMA.split(", ")]
        given = self.options.get("columns")
        return [c for c in every if c in given.split(",")] if given else every

    def schema(self) -> str:
        return ", ".join(c for c in SCHEMA.split(", ") if c.split()[0] in self.wanted())

    def reader(self, schema) -> WarcReader:
        return WarcReader(self.options["path"], [f.name for f in schema.fields])


def read_warc(spark: SparkSession, path: str, columns: list[str] | None = None) -> DataFrame:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcDataSource)
    reader = spark.read.format("warc")
    return (reader.option("columns", ",".join(columns)) if columns else reader).load(path)


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes all pages to archives and reads back what each record is; see ``write_warc``."""
    path = scratch_path(spark, "warc")
    write_warc(table(spark, sf_dir, "pages"), path)
    back = read_warc(spark, path, ["page_id", "record_type", "refers_to", "payload_digest", "payload_bytes", "computed_digest"])
    # a stored payload is hashed as it is read; a revisit has its payload's digest in its headers
    return back.select("page_id", "payload_bytes", F.coalesce("computed_digest", "payload_digest").alias("payload_digest"), "record_type", "refers_to")


OP4_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, strlen(h)::BIGINT AS payload_bytes, sha256(h) AS payload_digest FROM p),
f AS (SELECT payload_digest, min(page_id) AS first FROM d WHERE payload_bytes >= 100 GROUP BY ALL)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id <> first THEN first END AS refers_to
FROM d LEFT JOIN f USING (payload_digest)
"""
