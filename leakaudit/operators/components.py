"""Connected components of an edge list by randomised contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.runtime import materialise

MAX_ROUNDS = 100


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``(node, component)`` for every node of ``edges``; two nodes share a component iff a path joins them.

    Each round every node moves to the neighbour (or itself) of least random
    priority; edges are relabelled, loops and repeats dropped. The number of
    remaining edges falls geometrically, so rounds grow with the logarithm of the
    input. The component id is one of its own nodes, no particular one. Null ends,
    loops and repeated edges are allowed: a null end drops the edge, a loop yields
    its node as a component of its own. No edges: no rows.
    """
    ends = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u is not null and v is not null")
    left = materialise(ends.distinct(), "edges")
    nodes = None
    for turn in range(MAX_ROUNDS):
        both = left.union(left.select("v", "u"))
        if turn == 0:
            both = both.union(left.select("u", "u")).union(left.select("v", "v"))
        elif left.isEmpty():
            break
        rank = lambda c: F.struct(F.xxhash64(F.lit(turn), F.col(c)).alias("p"), F.col(c).alias("n"))  # noqa: E731, B023
        best = both.groupBy("u").agg(F.min(rank("v")).alias("m"))
        step = materialise(best.select("u", F.least("m", rank("u"))["n"].alias("to")), "step")
        nodes = step.select(F.col("u").alias("node"), F.col("to").alias("component")) if nodes is None else materialise(
            nodes.join(step, nodes["component"] == step["u"], "left").select("node", F.coalesce("to", "component").alias("component")), "nodes")
        to = step.select(F.col("u").alias("v"), F.col("to").alias("to_v"))
        left = materialise(left.join(step, "u").join(to, "v").where("to <> to_v").select(F.least("to", "to_v").alias("u"), F.greatest("to", "to_v").alias("v")).distinct(), "edges")
    else:
        raise RuntimeError("contraction did not end")
    return nodes
