"""Connected components of an edge table by repeated contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eventpulse.plans.scratch import discard, materialize


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node that has an edge; component = smallest reachable node.

    Each round hooks every node to its smallest neighbour, jumps pointers twice and
    contracts the edges onto the hooks, so the nodes that still have edges at least halve.
    All steps are aggregates with map-side minima or equi-joins that adaptive execution
    can split, so a hub with a third of the edges does not land in one task. Tables are
    written between rounds; nothing but a row count reaches the driver.

    Null endpoints are dropped; self loops and repeated edges change nothing; no edges
    give an empty table.
    """
    live = materialize(
        edges.select(F.least(src, dst).alias("u"), F.greatest(src, dst).alias("v"))
        .where("u is not null and v is not null and u <> v").distinct(),
        "cc-edges",
    )
    label: DataFrame | None = None
    for _ in range(max_rounds):
        hooks = (
            live.select("u", "v").unionAll(live.select(F.col("v").alias("u"), F.col("u").alias("v")))
            .groupBy("u").agg(F.min("v").alias("v"))
            .select(F.col("u").alias("node"), F.least("u", "v").alias("up"))
        )
        hooks = materialize(hooks, "cc-hooks")
        parent = hooks
        for _ in range(2):
            up = parent.select(F.col("node").alias("up"), F.col("up").alias("up2"))
            parent = parent.join(up, "up").select("node", F.col("up2").alias("up"))
        parent = materialize(parent, "cc-parent")
        a = parent.select(F.col("node").alias("u"), F.col("up").alias("pu"))
        b = parent.select(F.col("node").alias("v"), F.col("up").alias("pv"))
        rest = materialize(
            live.join(a, "u").join(b, "v").where("pu <> pv")
            .select(F.least("pu", "pv").alias("u"), F.greatest("pu", "pv").alias("v")).distinct(),
            "cc-edges",
        )
        if label is None:
            grown = parent.select("node", F.col("up").alias("component"))
        else:
            moved = parent.select(F.col("node").alias("component"), "up")
            grown = label.join(moved, "component", "left").select("node", F.coalesce("up", "component").alias("component"))
        new_label = materialize(grown, "cc-label")
        for old in (live, hooks, parent, label):
            discard(old)
        live, label = rest, new_label
        if live.isEmpty():
            discard(live)
            return label
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
