"""Connected components of a link table, without collecting links or components anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm.common import cut, drop, release


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("v", "u").cast("decimal(38,0)"))).first())


def components(spark: SparkSession, links: DataFrame, label: str = "components") -> DataFrame:
    """links (a, b) -> (id, component): the smallest id reachable, for every id that has a link.

    Rounds of two steps move every edge towards the smallest neighbour until each component is a star around its
    smallest id.  Minima are partial aggregates, so a hub's edges meet in no task; each round is cut.
    """
    edges = cut(spark, links.selectExpr("greatest(a, b) AS v", "least(a, b) AS u").where("v > u").distinct(), label)
    state = _state(edges)
    while state[0]:
        both = edges.selectExpr("v AS x", "u AS y").unionByName(edges.selectExpr("u AS x", "v AS y"))
        low = both.groupBy("x").agg(F.least(F.min("y"), F.col("x")).alias("m"))
        # every neighbour above x moves to the smallest id around x
        up = both.where("y > x").join(low, "x").selectExpr("y AS v", "m AS u").where("v > u")
        floor = up.groupBy("v").agg(F.min("u").alias("m"))
        # the smaller neighbours of v, and v, move to the smallest of them
        down = up.join(floor, "v").where("u > m").selectExpr("u AS v", "m AS u").unionByName(floor.selectExpr("v", "m AS u")).distinct()
        new = cut(spark, down, label)
        now = _state(new)
        drop(spark, edges)
        release(spark)
        edges = new
        if now == state:
            break
        state = now
    return edges.selectExpr("v AS id", "u AS component").unionByName(edges.selectExpr("u AS id", "u AS component").distinct())
