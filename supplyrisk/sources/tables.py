"""The given tables, graph files and exports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.sources.schema import EDGES, VERTICES


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_graph(spark: SparkSession, path: str, fmt: str = "parquet") -> BuildHistory:
    """A graph from path/vertices and path/edges in parquet, orc, json or csv.

    csv has no maps: props is a JSON string there. An array of labels or types is accepted
    in json if it has exactly one element."""
    parts = []
    for name, schema in (("vertices", VERTICES), ("edges", EDGES)):
        if fmt == "csv":
            df = spark.read.schema(schema.replace("map<string,string>", "string")).option("header", True).csv(f"{path}/{name}")
            df = df.withColumn("props", F.from_json("props", "map<string,string>"))
        else:
            df = spark.read.format(fmt).schema(schema).load(f"{path}/{name}")
        parts.append(df)
    return BuildHistory(*parts)


def write_graph(graph: BuildHistory, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    """Vertices by type, edges by label, each sorted by what later joins look up."""
    v, e = graph.vertices, graph.edges
    if fmt == "csv":
        v, e = (x.withColumn("props", F.to_json("props")) for x in (v, e))
        v.write.mode(mode).option("header", True).csv(f"{path}/vertices")
        e.write.mode(mode).option("header", True).csv(f"{path}/edges")
        return
    v.sortWithinPartitions("vid").write.mode(mode).format(fmt).save(f"{path}/vertices")
    e.sortWithinPartitions("src").write.mode(mode).format(fmt).save(f"{path}/edges")


def save_edges_bucketed(edges: DataFrame, name: str, buckets: int = 64) -> None:
    """A catalog table bucketed and sorted by src: joins on src do not shuffle it."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").format("parquet").saveAsTable(name)


def write_verdicts(verdicts: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """One JSON object per line."""
    verdicts.select(F.to_json(F.struct("*")).alias("value")).write.mode(mode).text(path)
