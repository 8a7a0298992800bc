"""SQL surface: views and functions over a build history."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.functions import udfs
from supplyrisk.operators.graph import BuildHistory


def register(spark: SparkSession, graph: BuildHistory, state: DataFrame | None = None) -> None:
    """Views bhg_vertices, bhg_edges and bhg_status (every vertex), and the SQL functions."""
    graph.vertices.createOrReplaceTempView("bhg_vertices")
    graph.edges.createOrReplaceTempView("bhg_edges")
    if state is not None:
        whole = graph.vertices.select("vid", "vtype").join(state, "vid", "left").select("vid", "vtype", F.coalesce("status", F.lit(0)).alias("status"))
        whole.createOrReplaceTempView("bhg_status")
    udfs.register(spark)
