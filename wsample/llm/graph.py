"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import written


def _least(edges: DataFrame) -> DataFrame:
    """(a, b) with the least neighbour of a."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    return edges.join(least, "a")


def large_star(edges: DataFrame) -> DataFrame:
    """Each node joins its larger neighbours to the least of its neighbourhood."""
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    return _least(both).where("b > a").select(F.col("b").alias("a"), F.least("a", "m").alias("b")).distinct()


def small_star(edges: DataFrame) -> DataFrame:
    """Each node joins its smaller neighbours and itself to the least of them."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    made = _least(down)
    return made.select(F.col("b").alias("a"), F.col("m").alias("b")).union(made.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, a: str, b: str, *, most_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of an edge that is not the least of its component.

    Rounds grow with the logarithm of the component size; each is written, so lineage stays short.
    Loops and repeated edges are allowed.
    """
    now = written(edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct(), "edges")
    state = _state(now)
    for _ in range(most_rounds):
        if not state[0]:
            break
        now = written(small_star(large_star(now)), "edges")
        state, before = _state(now), state
        if state == before:
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
