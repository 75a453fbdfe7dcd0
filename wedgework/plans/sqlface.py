"""The SQL face: views of a graph and parameterised statements."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators.csr import adjacency
from ..operators.prep import orient
from ..schema import Graph

STATEMENTS = {
    "triangles": "SELECT count(*) AS triangles FROM {oriented} x JOIN {oriented} y ON x.u = y.u JOIN {oriented} z ON z.u = x.v AND z.v = y.v",
    "lcc": """WITH t AS (SELECT x.u AS a, x.v AS b, z.v AS c FROM {oriented} x JOIN {oriented} y ON x.u = y.u JOIN {oriented} z ON z.u = x.v AND z.v = y.v),
        n AS (SELECT v, count(*) AS closed FROM (SELECT explode(array(a, b, c)) AS v FROM t) GROUP BY v), d AS (SELECT src AS v, count(*) AS deg FROM {arcs} GROUP BY src)
        SELECT d.v, d.deg, coalesce(n.closed, 0) AS closed, CASE WHEN d.deg >= 2 THEN 2.0D * coalesce(n.closed, 0) / (d.deg * (d.deg - 1)) END AS lcc FROM d LEFT JOIN n ON n.v = d.v""",
    "degree_at_least": "SELECT src AS v, count(*) AS deg FROM {arcs} GROUP BY src HAVING count(*) >= :least",
}


def register(spark: SparkSession, g: Graph, prefix: str = "") -> None:
    """Temporary views arcs and adj (with a prefix)."""
    g.arcs.createOrReplaceTempView(f"{prefix}arcs")
    adjacency(g).createOrReplaceTempView(f"{prefix}adj")


def run(g: Graph, statement: str, args: dict | None = None) -> DataFrame:
    frames = {"arcs": g.arcs} | ({"oriented": orient(g)} if "{oriented}" in STATEMENTS[statement] else {})
    return g.spark.sql(STATEMENTS[statement], args=args, **frames) if args else g.spark.sql(STATEMENTS[statement], **frames)
