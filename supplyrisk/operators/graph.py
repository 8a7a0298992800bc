"""Build histories: the typed graph, its checks and plain graph helpers."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supplyrisk.functions.rules import LEGAL
from supplyrisk.sources.schema import VERTEX_TYPES


@dataclass
class BuildHistory:
    """vertices: vid, vtype, akey, props. edges: eid, src, dst, label, props."""

    vertices: DataFrame
    edges: DataFrame

    def typed_edges(self) -> DataFrame:
        """Edges with src_type, dst_type (null: no such vertex)."""
        kind = self.vertices.select("vid", "vtype")
        out = self.edges.join(kind.withColumnsRenamed({"vid": "src", "vtype": "src_type"}), "src", "left")
        return out.join(kind.withColumnsRenamed({"vid": "dst", "vtype": "dst_type"}), "dst", "left")

    def validate(self, strict: bool = False) -> DataFrame:
        """eid, reason of each illegal edge; strict also reports edges from unknown vertices."""
        rules = self.vertices.sparkSession.createDataFrame(LEGAL, "label string, src_type string, dst_type string").withColumn("legal", F.lit(True))
        checked = self.typed_edges().join(F.broadcast(rules), ["label", "src_type", "dst_type"], "left")
        known = F.col("label").isin(*{x[0] for x in LEGAL})
        reason = (
            F.when(F.col("label").isNull() | ~known, "unknown label")
            .when(F.col("dst_type").isNull(), "unknown target")
            .when(F.col("src_type").isNull(), F.when(F.lit(strict), "unknown source"))
            .when(F.col("legal").isNull(), "illegal endpoints")
        )
        return checked.select("eid", reason.alias("reason")).where("reason is not null")

    def check_identity(self) -> DataFrame:
        """id, reason: ids shared by a vertex and an edge, repeated ids, unknown types."""
        v, e = self.vertices.select(F.col("vid").alias("id")), self.edges.select(F.col("eid").alias("id"))
        both = v.intersect(e).select("id", F.lit("vertex and edge").alias("reason"))
        twice = [x.groupBy("id").count().where("count > 1").select("id", F.lit(f"repeated {name}").alias("reason")) for x, name in ((v, "vertex"), (e, "edge"))]
        odd = self.vertices.where(F.col("vtype").isNull() | ~F.col("vtype").isin(*VERTEX_TYPES)).select(F.col("vid").alias("id"), F.lit("unknown type").alias("reason"))
        return both.union(twice[0]).union(twice[1]).union(odd)

    def parents_of(self, vids: DataFrame, labels: list[str] | None = None) -> DataFrame:
        """vid, parent, label of each in-edge of the given vids; parallel edges stay."""
        edges = self.edges if labels is None else self.edges.where(F.col("label").isin(*labels))
        return edges.join(vids.select(F.col("vid").alias("dst")), "dst").select(F.col("dst").alias("vid"), F.col("src").alias("parent"), "label")

    def degree(self, direction: str = "in", by_label: bool = False) -> DataFrame:
        """vid (, label), degree; isolated vertices have 0 (only without by_label)."""
        ends = {"in": ["dst"], "out": ["src"], "both": ["src", "dst"]}[direction]
        one = [self.edges.select(F.col(c).alias("vid"), "label") for c in ends]
        all_ends = one[0] if len(one) == 1 else one[0].unionAll(one[1])
        if by_label:
            return all_ends.groupBy("vid", "label").agg(F.count("*").alias("degree"))
        counted = all_ends.groupBy("vid").agg(F.count("*").alias("degree"))
        return self.vertices.select("vid").join(counted, "vid", "left").select("vid", F.coalesce("degree", F.lit(0)).alias("degree"))

    def roots(self) -> DataFrame:
        return self.vertices.join(self.edges.select(F.col("dst").alias("vid")), "vid", "left_anti").select("vid")

    def sinks(self) -> DataFrame:
        return self.vertices.join(self.edges.select(F.col("src").alias("vid")), "vid", "left_anti").select("vid")

    def subgraph(self, labels: list[str] | None = None, vtypes: list[str] | None = None) -> BuildHistory:
        """Induced on vertices of the types, with edges of the labels between them."""
        v = self.vertices if vtypes is None else self.vertices.where(F.col("vtype").isin(*vtypes))
        e = self.edges if labels is None else self.edges.where(F.col("label").isin(*labels))
        if vtypes is not None:
            ids = v.select("vid")
            e = e.join(ids.withColumnRenamed("vid", "src"), "src", "left_semi").join(ids.withColumnRenamed("vid", "dst"), "dst", "left_semi")
        return BuildHistory(v, e.select("eid", "src", "dst", "label", "props"))
