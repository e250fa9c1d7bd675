"""A Python data source of WARC-like records, and sinks that are read back."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from doccurate.plans.registry import query
from doccurate.sources.tables import shared_folder

_MARK = b"WARC/1.0\r\n"


class ArchiveSource(DataSource):
    """Files of records: a mark, header lines, an empty line, ``Content-Length`` bytes; one partition a file.

    Options: ``path``, a folder that every executor can read (a local or mounted one, or what pyarrow.fs opens).
    """

    @classmethod
    def name(cls) -> str:
        return "archive_records"

    def schema(self) -> str:
        return "file string, url string, payload binary"

    def reader(self, schema) -> ArchiveReader:
        return ArchiveReader(self.options["path"])


class ArchiveReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path)
        return [InputPartition(f.path) for f in system.get_file_info(fs.FileSelector(root)) if f.path.endswith(".warc")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from pyarrow import fs

        system = fs.FileSystem.from_uri(self.path)[0] if "://" in self.path else fs.LocalFileSystem()
        with system.open_input_stream(partition.value) as f:
            data = f.read()
        at = 0
        while (at := data.find(_MARK, at)) >= 0:
            body = data.index(b"\r\n\r\n", at) + 4
            head = dict(line.split(": ", 1) for line in data[at + len(_MARK) : body - 4].decode().split("\r\n"))
            size = int(head["Content-Length"])
            yield partition.value.rsplit("/", 1)[-1], head["WARC-Target-URI"], data[body : body + size]
            at = body + size


def write_archives(pages: DataFrame, path: str, files: int = 4) -> None:
    """Records of pages(url, html) as archive files in a folder that all executors share."""

    def run(batches):
        from pyarrow import fs
        from pyspark import TaskContext

        system, root = fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)
        system.create_dir(root, recursive=True)
        with system.open_output_stream(f"{root}/{TaskContext.get().partitionId():05d}.warc") as f:
            for b in batches:
                for url, html in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    body = (html or "").encode()
                    f.write(_MARK + f"WARC-Target-URI: {url}\r\nContent-Length: {len(body)}\r\n\r\n".encode() + body + b"\r\n\r\n")
        yield from ()

    pages.select("url", "html").repartition(files).mapInArrow(run, "done int").count()


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/sink-{uuid.uuid4().hex}"


@query("op_source_archives", "SELECT url, strlen(html) AS bytes, md5(html) AS body FROM pages")
def archives(spark, sf_dir):
    folder = _folder(spark)
    write_archives(spark.read.parquet(f"{sf_dir}/pages.parquet"), folder)
    spark.dataSource.register(ArchiveSource)
    read = spark.read.format("archive_records").option("path", folder).load()
    return read.select("url", F.octet_length("payload").cast("long").alias("bytes"), F.md5("payload").alias("body"))


@query("op_sink_roundtrip", "SELECT f AS format, count(*) AS n, sum(length(text))::BIGINT AS chars FROM documents, (VALUES ('csv'), ('json'), ('orc'), ('parquet'), ('text')) AS t(f) GROUP BY f")
def roundtrip(spark, sf_dir):
    """Documents written in each format (JSON lines in shards, Parquet by language) and read back."""
    docs, folder, out = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "text"), _folder(spark), None
    one_line = docs.withColumn("text", F.to_json(F.struct("text")))
    docs.write.partitionBy("lang").parquet(f"{folder}/parquet")
    docs.write.option("maxRecordsPerFile", 500).json(f"{folder}/json")
    docs.write.orc(f"{folder}/orc")
    one_line.write.option("escape", '"').csv(f"{folder}/csv", header=True)
    one_line.select("text").write.text(f"{folder}/text")
    back = {
        "parquet": spark.read.parquet(f"{folder}/parquet").select("text"),
        "json": spark.read.schema("doc_id long, lang string, text string").json(f"{folder}/json").select("text"),
        "orc": spark.read.orc(f"{folder}/orc").select("text"),
        "csv": spark.read.schema("doc_id long, lang string, text string").option("escape", '"').csv(f"{folder}/csv", header=True).select(F.from_json("text", "text string").text.alias("text")),
        "text": spark.read.text(f"{folder}/text").select(F.from_json("value", "text string").text.alias("text")),
    }
    for name, rows in back.items():
        one = rows.agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars")).select(F.lit(name).alias("format"), "n", "chars")
        out = one if out is None else out.unionByName(one)
    return out


