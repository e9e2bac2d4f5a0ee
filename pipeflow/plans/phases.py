"""Phases: connected components without blocking edges, in a topological order; on the driver or in bulk."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pipeflow.plans.graph import BLOCKING, PULL, Edge, FlowGraph, FlowGraphError
from pipeflow.plans.validate import check, contracted, joined, needs_delay, self_blocked, topological
from pipeflow.session import materialise


def order(g: FlowGraph) -> list[list[str]]:
    """The phases' nodes, phases in the order in which they run."""
    check(g)
    of = joined(g)
    roots, stuck = topological([n for n in g.names if of[n] == n], contracted(g))
    if stuck:
        raise FlowGraphError(f"phase_cycle: {', '.join(stuck)}")
    return [[n for n in g.names if of[n] == r] for r in roots]


def identify(g: FlowGraph) -> dict[str, int]:
    """node -> number of its phase, from 1."""
    return {n: k for k, names in enumerate(order(g), 1) for n in names}


def insert_delays(g: FlowGraph, pulled: bool = False) -> FlowGraph:
    """Repairs a graph whose blocking halves lie in one phase: delays go on push edges around them.

    Of the edges that help, the one into the node that pulls the blocking output is taken, else the first.
    """
    made = 0
    while blocked := self_blocked(g):
        edges = needs_delay(g)
        if not edges:
            raise FlowGraphError(f"no delay separates the halves of {', '.join(blocked)}")
        pullers = {e.dst for e in g.edges if e.kind == PULL}
        edge = next((e for e in edges if e.dst in pullers), edges[0])
        made += 1
        name = f"D{made}"
        g = g.without(edge).blocking(name)
        g.edges += [Edge(edge.src, f"{name}i", edge.kind), Edge(f"{name}o", edge.dst, PULL if pulled else edge.kind)]
    return g


def identify_df(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """nodes (graph, node), edges (graph, src, dst, kind) of many graphs -> (graph, node, phase): the least node that streaming edges connect.

    Rounds of least labels among neighbours with pointer jumping: a chain of n nodes takes O(log n) rounds. A table is
    written to the shared folder each round; the driver sees whether any label moved.
    """
    links = edges.where(F.col("kind") != BLOCKING).select("graph", F.col("src").alias("a"), F.col("dst").alias("b"))
    links = materialise(links.union(links.select("graph", "b", "a")).distinct(), "links")
    state = materialise(nodes.select("graph", "node", F.col("node").alias("phase")), "phase")
    while True:
        near = links.join(state.select("graph", F.col("node").alias("b"), "phase"), ["graph", "b"]).groupBy("graph", F.col("a").alias("node")).agg(F.min("phase").alias("near"))
        hook = state.join(near, ["graph", "node"], "left").groupBy("graph", "phase").agg(F.min(F.least("phase", F.coalesce("near", "phase"))).alias("to"))
        hook = materialise(hook, "hook")
        jump = hook.join(hook.select("graph", F.col("phase").alias("to"), F.col("to").alias("next")), ["graph", "to"], "left").select("graph", "phase", F.coalesce("next", "to").alias("label"))
        new = materialise(state.join(jump, ["graph", "phase"]).select("graph", "node", F.col("label").alias("phase"), (F.col("label") != F.col("phase")).alias("moved")), "phase")
        if not new.where("moved").limit(1).count():
            return new.drop("moved")
        state = new.drop("moved")


def order_df(phases: DataFrame, edges: DataFrame) -> DataFrame:
    """(graph, phase, level): the longest path of blocking edges to each phase. As many rounds as the deepest graph has phases."""
    src, dst = (phases.select("graph", F.col("node").alias(c), F.col("phase").alias(f"{c}_phase")) for c in ("src", "dst"))
    hops = edges.where(F.col("kind") == BLOCKING).join(src, ["graph", "src"]).join(dst, ["graph", "dst"]).select("graph", F.col("src_phase").alias("p"), F.col("dst_phase").alias("q")).where("p != q").distinct()
    hops = materialise(hops, "hops")
    every = materialise(phases.select("graph", "phase").distinct(), "every")
    level = every.withColumn("level", F.lit(0).cast("long"))
    front, k, most = level, 0, every.count()
    while True:
        front = materialise(hops.join(front.select("graph", F.col("phase").alias("p")), ["graph", "p"]).select("graph", F.col("q").alias("phase")).distinct(), "front")
        if not front.limit(1).count():
            return level
        k += 1
        if k > most:
            raise FlowGraphError("phase_cycle: a bulk graph has a cycle of phases")
        level = materialise(level.join(front.withColumn("k", F.lit(k).cast("long")), ["graph", "phase"], "left").select("graph", "phase", F.coalesce("k", "level").alias("level")), "level")


def violations_df(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(graph, rule, node) of the local rules in bulk: nodes with both kinds of outgoing edges, unpaired halves, self-blocked ones."""
    mixed = edges.where(F.col("kind") != BLOCKING).groupBy("graph", "src").agg(F.count_distinct("kind").alias("n")).where("n > 1").select("graph", F.lit("mixed_out").alias("rule"), F.col("src").alias("node"))
    blocking = edges.where(F.col("kind") == BLOCKING)
    lone_in = nodes.where("kind = 'input'").join(blocking.select("graph", F.col("src").alias("node")), ["graph", "node"], "left_anti")
    lone_out = nodes.where("kind = 'output'").join(blocking.select("graph", F.col("dst").alias("node")), ["graph", "node"], "left_anti")
    lone = lone_in.unionByName(lone_out).select("graph", F.lit("block_pairs").alias("rule"), "node")
    of = identify_df(nodes, edges)
    a, b = (of.select("graph", F.col("node").alias(c), F.col("phase").alias(f"{c}_phase")) for c in ("src", "dst"))
    blocked = blocking.join(a, ["graph", "src"]).join(b, ["graph", "dst"]).where("src_phase = dst_phase").select("graph", F.lit("self_blocked").alias("rule"), F.col("src").alias("node"))
    return mixed.unionByName(lone).unionByName(blocked)
