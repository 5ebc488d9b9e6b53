"""Pages to packaged web archives in the shared folder, and back.

Of pages with equal payloads of at least `least` bytes the one with the largest id is a response and the others
revisit it; all others are responses. Roles are found from digests and ids alone and joined back by both, so a
payload that a third of the pages share makes no heavy key; each task then writes packages of about `package`
bytes. The table of written packages is kept before anything is read, so a task that ran twice leaves a file
that no one reads, not a record too many.

Null payloads are empty ones. Rows that repeat an id and its payload are records of their own, all responses if
the id is the largest of its payload. Ids that are null never become the response of a payload that also has
ids; if none has, its records are responses.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks, cut, shared_path
from boxsum.llm.zip_archive import PackageWriter, Record, digest, records

PACKAGE = 16 << 20
#: Packages that a reading task takes at most, where there are more tasks than cores anyway.
A_TASK = 8
#: Writing tasks whose packages are told in one part of the table of packages.
A_PART = 64


def roles(pages: DataFrame, least: int = 0) -> DataFrame:
    """pages (id, uri, html) with kind and refers_to. html must not be null."""
    size = F.octet_length("html")
    keyed = pages.select("id", F.sha1(F.col("html").cast("binary")).alias("sha"), size.alias("size"))
    owner = keyed.groupBy("sha", "size").agg(F.max("id").alias("owner"))
    revisits = keyed.where(F.col("size") >= least).join(owner, ["sha", "size"]).where("id is null and owner is not null or id < owner").select(F.col("id").alias("of"), F.col("sha").alias("of_sha"), "owner").distinct()
    both = pages.withColumn("sha", F.sha1(F.col("html").cast("binary"))).join(revisits, F.col("id").eqNullSafe(F.col("of")) & (F.col("sha") == F.col("of_sha")), "left")
    return both.select("id", "uri", "html", F.when(F.col("owner").isNull(), "response").otherwise("revisit").alias("kind"), F.col("owner").alias("refers_to"))


def write_packages(pages: DataFrame, root: str | None = None, id_col: str = "page_id", uri_col: str = "url", html_col: str = "html", least: int = 0, package: int = PACKAGE) -> DataFrame:
    """(path, bytes, records) of the packages written under root, by default a new path in the shared folder."""
    root = root or shared_path(pages.sparkSession, "packages")
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(uri_col).cast("string"), F.lit("")).alias("uri"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = fs.FileSystem.from_uri(root)
        store.create_dir(base, recursive=True)

        def finish(w: PackageWriter) -> pa.RecordBatch:
            path, data = f"{base}/{uuid.uuid4().hex}.wacz", w.close()
            with store.open_output_stream(path + ".part") as f:
                f.write(data)
            store.move(path + ".part", path)
            return pa.RecordBatch.from_arrays([pa.array([path.rsplit("/", 1)[1]]), pa.array([len(data)], pa.int64()), pa.array([len(w.lines)], pa.int64())], ["path", "bytes", "records"])

        w = PackageWriter()
        for b in blocks(batches, "html"):
            for page, uri, html, kind, refers in zip(*(c.to_pylist() for c in b.columns), strict=True):
                payload = html.encode("utf-8", "surrogatepass")
                w.add(Record(kind, page, uri, payload if kind == "response" else b"", digest(payload), len(payload), refers))
                if w.size >= package:
                    yield finish(w)
                    w = PackageWriter()
        if w.lines:
            yield finish(w)

    written = roles(rows, least).mapInArrow(run, "path string, bytes long, records long")
    # a task that is run again names other files, so all that it tells must go to one part, which holds one run of it
    told = written.withColumn("task", F.spark_partition_id())
    parts = -(-int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions")) // A_PART)
    return cut(told.repartition(parts, "task").select(F.concat(F.lit(root.rstrip("/") + "/"), "path").alias("path"), "bytes", "records"))


def read_packages(packages: DataFrame, with_payload: bool = False) -> DataFrame:
    """(page_id, url, payload_bytes, payload_digest, record_type, refers_to[, payload]) of every record of the packages (path).

    Packages are read in parallel, at most `A_TASK` by a task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path in b.column("path").to_pylist():
                store, at = fs.FileSystem.from_uri(path)
                with store.open_input_file(at) as source:
                    rows: list[tuple] = []
                    held = 0
                    for r in records(source, source.size()):
                        rows.append((r.page, r.uri, r.payload_bytes, r.payload_digest, r.kind, r.refers_to, *([r.payload if r.kind == "response" else None] if with_payload else [])))
                        held += len(r.payload) if with_payload else 0
                        if len(rows) >= 10_000 or held > PACKAGE:
                            yield batch(rows)
                            rows, held = [], 0
                    if rows:
                        yield batch(rows)

    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]

    def batch(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=False)], names[: len(rows[0])])

    schema = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long" + (", payload binary" if with_payload else "")
    # paths are small rows that stand for large files, so their number is what tasks are dealt by
    spark = packages.sparkSession
    n = packages.count()
    tasks = max(1, min(n, max(-(-n // A_TASK), 4 * spark.sparkContext.defaultParallelism)))
    return packages.select("path").repartitionByRange(tasks, "path").mapInArrow(run, schema)
