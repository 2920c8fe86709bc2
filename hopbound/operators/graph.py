"""A directed simple graph as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass
class Graph:
    """edges has src, dst, and usually ord (scan order within src) and w; nodes are those on an edge unless given."""

    edges: DataFrame
    given: DataFrame | None = None

    @property
    def nodes(self) -> DataFrame:
        on = self.edges.select(F.col("src").alias("id")).unionByName(self.edges.select(F.col("dst").alias("id")))
        return (on if self.given is None else on.unionByName(self.given.select("id"))).distinct()

    def simplify(self) -> Graph:
        """No loops, no null ends, parallel edges merged (w summed, else counted)."""
        e = self.edges.where("src IS NOT NULL AND dst IS NOT NULL AND src <> dst")
        w = F.sum("w") if "w" in e.columns else F.count(F.lit(1))
        keep = [F.min("ord").alias("ord")] if "ord" in e.columns else []
        return Graph(e.groupBy("src", "dst").agg(w.alias("w"), *keep), self.given)

    def ordered(self, *key: str | Column) -> Graph:
        """ord by key (dst unless given) within src: the only source of scan order."""
        w = Window.partitionBy("src").orderBy(*(key or ("dst",)))
        return Graph(self.edges.withColumn("ord", F.row_number().over(w)), self.given)

    def reverse(self) -> Graph:
        return Graph(self.edges.withColumnsRenamed({"src": "_s", "dst": "src"}).withColumnRenamed("_s", "dst"), self.given)

    def symmetrize(self) -> Graph:
        e = self.edges.select("src", "dst")
        return Graph(e.union(e.select("dst", "src")).distinct(), self.given).ordered()

    def induced(self, nodes: DataFrame) -> Graph:
        """Edges both of whose ends are among nodes (id)."""
        a, b = nodes.select(F.col("id").alias("src")).distinct(), nodes.select(F.col("id").alias("dst")).distinct()
        return Graph(self.edges.join(a, "src", "left_semi").join(b, "dst", "left_semi").select(*self.edges.columns))

    def where(self, condition: str | Column) -> Graph:
        return Graph(self.edges.where(condition), self.given)

    def split_node(self, s, out, back) -> Graph:
        """s replaced by `out`, which keeps its successors, and `back`, which keeps its predecessors."""
        e = self.edges.withColumns({"src": F.when(F.col("src") == s, F.lit(out)).otherwise(F.col("src")), "dst": F.when(F.col("dst") == s, F.lit(back)).otherwise(F.col("dst"))})
        return Graph(e, self.given)

    def super_sink(self, targets: DataFrame, sink) -> Graph:
        """An edge, scanned last, from every target (id) to a new node."""
        more = targets.select(F.col("id").alias("src"), F.lit(sink).alias("dst"), F.lit(2_000_000_000).alias("ord"))
        return Graph(self.edges.select("src", "dst", "ord").unionByName(more), self.given)

    def degrees(self) -> DataFrame:
        """id, out_degree, in_degree; nodes without either edge count 0."""
        out = self.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("out_degree"))
        into = self.edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("in_degree"))
        return out.join(into, "id", "full_outer").select("id", F.coalesce("out_degree", F.lit(0)).alias("out_degree"), F.coalesce("in_degree", F.lit(0)).alias("in_degree"))

    def density(self) -> DataFrame:
        n, m = self.nodes.agg(F.count(F.lit(1)).alias("n")), self.edges.agg(F.count(F.lit(1)).alias("m"))
        return n.crossJoin(m).select("n", "m", F.when(F.col("n") > 1, F.round(F.col("m") / (F.col("n") * (F.col("n") - 1)), 6)).alias("density"))
