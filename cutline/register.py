"""SQL surface: temporary views of the stand-in graphs, table functions, and the file format."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .functions.cutter import directions
from .sources import graphs
from .sources.dimacs import DimacsSource


@udtf(returnType="k int, cx bigint, cy bigint")
class SweepDirections:
    """sweep_directions(q): the fixed-point directions of q cutters."""

    def eval(self, q: int):
        for k, (c, s) in enumerate(directions(q)):
            yield k, c, s


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """`dimacs` as a format, `sweep_directions` as a table function, and g_<name>_nodes / g_<name>_edges as views over sf_dir."""
    spark.dataSource.register(DimacsSource)
    spark.udtf.register("sweep_directions", SweepDirections)
    for name in graphs.TABLES if sf_dir else ():
        g = graphs.graph(spark, sf_dir, name)
        g.nodes.createOrReplaceTempView(f"g_{name}_nodes")
        g.edges.createOrReplaceTempView(f"g_{name}_edges")
