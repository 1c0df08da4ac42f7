"""Connected components of an edge table, as rounds of joins and aggregates over tables in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import written


def _after(parents: DataFrame, step: DataFrame) -> DataFrame:
    """Follow one more step from each vertex's present parent."""
    both = parents.alias("o").join(step.alias("n"), F.col("o.p") == F.col("n.v"), "left")
    return both.select(F.col("o.v").alias("v"), F.coalesce("n.p", "o.p").alias("p"))


def components(edges: DataFrame, *, rounds: int = 80) -> DataFrame:
    """v and root (the smallest vertex that it can reach) for every vertex of edges(a, b).

    Each round every vertex picks the vertex of its closed neighbourhood with the smallest draw, a fresh one in each round, and
    the edges are replaced by those between the picks. Which picks survive is random, so long chains shrink by a constant
    factor in each round too, and the number of rounds grows with the logarithm of the graph. All rounds work on the
    shrinking edge table; no vertex list goes to the driver.
    """
    live = written(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    parents: DataFrame | None = None
    for number in range(rounds):
        if live.isEmpty():
            break
        draw = lambda c, number=number: F.struct(F.xxhash64(F.col(c), F.lit(number)).alias("draw"), F.col(c).alias("p"))
        both = live.unionByName(live.select(F.col("b").alias("a"), F.col("a").alias("b")))
        step = written(both.groupBy(F.col("a").alias("v")).agg(F.min(draw("b")).alias("d")).select("v", F.least(F.col("d"), draw("v"))["p"].alias("p")), "picks")
        parents = step if parents is None else written(_after(parents, step), "picks")
        moved = live.join(step.select(F.col("v").alias("a"), F.col("p").alias("pa")), "a").join(step.select(F.col("v").alias("b"), F.col("p").alias("pb")), "b")
        live = written(moved.where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(), "edges")
    else:
        raise RuntimeError("the components didn't settle")
    if parents is None:
        return live.select(F.col("a").alias("v"), F.col("a").alias("root"))
    roots = parents.groupBy("p").agg(F.min("v").alias("root"))
    return parents.join(roots, "p").select("v", "root")
