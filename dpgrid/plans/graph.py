"""Connected components of a distributed edge list by randomised contraction.

Each round every vertex follows the neighbour (or itself) with the least hash of that round; edges
are then rewritten between the chosen vertices and loops drop out. The edge list shrinks by a
constant factor in expectation whatever the shape of the graph, so long paths need as few rounds as
stars. Hot vertices cost nothing special: choosing is a map-side combined minimum, and rewriting is a
plain equi-join that adaptive execution can split.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpgrid.plans.scratch import drop_tables, materialise


def _pick(vertex: str, priority_seed: int) -> Column:
    return F.struct(F.xxhash64(F.col(vertex), F.lit(priority_seed)).alias("p"), F.col(vertex).alias("v"))


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 64) -> DataFrame:
    """``edges(src, dst)`` of longs → ``(vertex, component)``, component = least vertex of the component.

    Loops, repeated and reversed edges are harmless; an edge with a null end is ignored. Vertices
    without a proper edge do not occur in the result. An empty edge list gives an empty table.
    """
    live = materialise(
        edges.select(F.least(src, dst).cast("long").alias("a"), F.greatest(src, dst).cast("long").alias("b"))
        .where("a is not null and b is not null and a <> b")
        .distinct(),
        "cc_edges",
    )
    hops: list[DataFrame] = []
    for turn in range(max_rounds):
        if live.isEmpty():
            break
        both = live.select(F.col("a").alias("u"), F.col("b").alias("w")).union(live.select(F.col("b").alias("u"), F.col("a").alias("w")))
        hop = materialise(
            both.groupBy("u")
            .agg(F.min(_pick("w", turn)).alias("best"))
            .select("u", F.least(F.col("best"), _pick("u", turn))["v"].alias("to")),
            "cc_hop",
        )
        hops.append(hop)
        left = hop.select(F.col("u").alias("a"), F.col("to").alias("ta"))
        right = hop.select(F.col("u").alias("b"), F.col("to").alias("tb"))
        shrunk = materialise(
            live.join(left, "a").join(right, "b").where("ta <> tb")
            .select(F.least("ta", "tb").alias("a"), F.greatest("ta", "tb").alias("b"))
            .distinct(),
            "cc_edges",
        )
        drop_tables(live.sparkSession, live)
        live = shrunk
    else:
        raise RuntimeError("contraction did not end")
    if not hops:
        return live.select(F.col("a").alias("vertex"), F.col("b").alias("component"))
    labels = hops[0].select(F.col("u").alias("vertex"), F.col("to").alias("root"))
    for hop in hops[1:]:
        labels = labels.join(hop.select(F.col("u").alias("root"), "to"), "root", "left").select("vertex", F.coalesce("to", "root").alias("root"))
    labels = materialise(labels, "cc_labels")
    drop_tables(labels.sparkSession, *hops)
    least = materialise(labels.groupBy("root").agg(F.min("vertex").alias("component")), "cc_least")
    return labels.join(least, "root").select("vertex", "component")
