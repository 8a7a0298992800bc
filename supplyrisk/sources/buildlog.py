"""Build logs: JSON lines, one build record each, as a Python data source.

A record names its step and optionally env, host, inputs, tools, present (artifacts in the
environment), outputs, fetched ({artifact, host}) and published ({artifact, host}); what is
missing or null makes no edge. A line that is no record fails the query, with its place.
"""

from __future__ import annotations

import io
import json
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.plans.staging import shared_dir
from supplyrisk.sources.schema import BASE, ENV, STEP, STORAGE, hashed

SCHEMA = "label string, src_type string, src string, dst_type string, dst string"
CODES = {"artifact": BASE, "step": STEP, "env": ENV, "host": STORAGE}


def edges_of(record: dict) -> Iterator[tuple[str, str, str, str, str]]:
    """The edges (as in SCHEMA) of one build record."""
    step, env, host = record["step"], record.get("env"), record.get("host")
    for name, label in (("inputs", "feeds"), ("tools", "tools")):
        for artifact in record.get(name) or ():
            yield label, "artifact", artifact, "step", step
    for artifact in record.get("outputs") or ():
        yield "produces", "step", step, "artifact", artifact
    if env is not None:
        yield "runs_step", "env", env, "step", step
        for artifact in record.get("present") or ():
            yield "present_in", "artifact", artifact, "env", env
        if host is not None:
            yield "hosts_env", "host", host, "env", env
    for x in record.get("fetched") or ():
        yield "fetched_from", "host", x["host"], "artifact", x["artifact"]
    for x in record.get("published") or ():
        yield "published_to", "artifact", x["artifact"], "host", x["host"]


class Range(InputPartition):
    """The lines of a file that begin at or after start and before stop."""

    def __init__(self, path: str, start: int, stop: int):
        self.path, self.start, self.stop = path, start, stop


class BuildLogReader(DataSourceReader):
    def __init__(self, path: str, chunk_bytes: int):
        self.path, self.chunk_bytes = path, chunk_bytes

    def _files(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path)

    def partitions(self) -> list[Range]:
        """Files are cut by bytes, so a long log is many tasks."""
        from pyarrow import fs

        system, root = self._files()
        info = system.get_file_info(root)
        if info.type == fs.FileType.NotFound:
            raise FileNotFoundError(self.path)
        files = [info] if info.is_file else system.get_file_info(fs.FileSelector(root, recursive=True))
        files = [f for f in files if f.is_file and not f.base_name.startswith(("_", "."))]
        return [Range(f.path, at, min(at + self.chunk_bytes, f.size)) for f in files for at in range(0, f.size, self.chunk_bytes)] or [Range("", 0, 0)]

    def read(self, partition: Range) -> Iterator[tuple]:
        if not partition.path:
            return
        with io.BufferedReader(self._files()[0].open_input_file(partition.path), 1 << 20) as file:
            at = partition.start
            if at:  # a line that began before belongs to the range before
                file.seek(at - 1)
                at += len(file.readline()) - 1
            file.seek(at)
            while at < partition.stop:
                line = file.readline()
                if line.strip():
                    try:
                        found = list(edges_of(json.loads(line)))
                    except (ValueError, KeyError, TypeError, AttributeError) as e:
                        raise ValueError(f"no build record at byte {at} of {partition.path}: {e!r}") from e
                    yield from found
                at += len(line)


class BuildLog(DataSource):
    """spark.read.format("buildlog").load(path). Option chunk_bytes: size of a task's range."""

    @classmethod
    def name(cls) -> str:
        return "buildlog"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> BuildLogReader:
        return BuildLogReader(self.options["path"], int(self.options.get("chunk_bytes", 64 << 20)))


def read(spark: SparkSession, path: str, chunk_bytes: int = 64 << 20) -> DataFrame:
    """Edges by name, as often as records state them."""
    spark.dataSource.register(BuildLog)
    return spark.read.format("buildlog").option("chunk_bytes", str(chunk_bytes)).load(path)


def write(records: DataFrame, path: str | None = None) -> str:
    """Records as JSON lines at path, or in a new folder of the shared one; returns where."""
    path = path or f"{shared_dir(records.sparkSession)}/buildlog-{uuid.uuid4().hex}"
    records.write.json(path)
    return path


def graph(edges: DataFrame) -> BuildHistory:
    """A build history of edges by name; ids are hashes of type and name, and a name is an
    artifact's identity."""
    kinds = F.explode(F.array(F.struct(F.col("src_type").alias("vtype"), F.col("src").alias("name")), F.struct(F.col("dst_type").alias("vtype"), F.col("dst").alias("name")))).alias("v")
    names = edges.select(kinds).select("v.*").distinct()
    none = F.lit(None).cast("map<string,string>").alias("props")
    vertices = names.select(_id("vtype", "name").alias("vid"), "vtype", F.when(F.col("vtype") == "artifact", F.col("name")).alias("akey"), none)
    distinct = edges.distinct()
    eid = F.xxhash64("label", "src_type", "src", "dst_type", "dst").alias("eid")
    return BuildHistory(vertices, distinct.select(eid, _id("src_type", "src").alias("src"), _id("dst_type", "dst").alias("dst"), "label", none))


def _id(kind: str, name: str):
    out = F.raise_error(F.concat(F.lit("unknown type "), F.col(kind))).cast("long")
    for vtype, code in CODES.items():
        out = F.when(F.col(kind) == vtype, hashed(code, F.col(name))).otherwise(out)
    return out
