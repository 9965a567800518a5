"""Which method to take for a graph and a number of cores."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from minlabel.graph import Graph, joined_to
from minlabel.operators import mapping
from minlabel.session import stored


@dataclass(frozen=True)
class Recommendation:
    method: str
    order: int
    reason: str


# Thresholds of our own, after the advice that small diameters favour low orders and large ones high orders.
FEW_HOPS, SOME_HOPS, MIXED, MUCH_WORK, BYTES_AN_ID = 4, 64, 0.2, 50_000_000, 16


def recommend_method(stats: dict, cores: int, finished_share: float = 0.0, executor_bytes: int = 8 << 30) -> Recommendation:
    """stats: n, m, diameter_lb; finished_share: vertices whose component was done after two rounds."""
    if stats["m"] / max(cores, 1) > MUCH_WORK and stats["n"] * BYTES_AN_ID < executor_bytes:
        return Recommendation("union_find", 0, "much work for each core, and all ids fit one task")
    if 0.5 < finished_share < 1:
        return Recommendation("low_then_high", 1024, "most components are tiny, a few are long")
    if MIXED < finished_share < 1 and stats["diameter_lb"] <= SOME_HOPS:
        return Recommendation("alternate", 1024, "some components are done, others go on: cheap rounds with long ones between")
    if stats["diameter_lb"] <= FEW_HOPS:
        return Recommendation("order1", 1, "few hops: the cheapest rounds")
    if stats["diameter_lb"] <= SOME_HOPS:
        return Recommendation("order2", 2, "stable and cheap")
    return Recommendation("orderm", 1024, "large diameter: fewest rounds")


def sampled_stats(g: Graph, rounds: int = 2) -> tuple[dict, float]:
    """n, m and a least diameter, and the share of vertices whose component was done after some rounds, from these rounds of order 1 alone: after k of them a label that lowers yet has come k hops at least. So advice costs a few cheap rounds, not a solution."""
    n = int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    directed, labels = g.prepared(n), mapping.init_labels(g.vertices)
    hops, open_ = 0, None
    for k in range(1, rounds + 1):
        out = stored(mapping.step(directed, labels, 1))
        changed = out.where("label < before").count()
        labels = out.select("id", "label")
        if not changed:
            break
        hops = k
    ends = joined_to(directed, labels.select(F.col("id").alias("src"), F.col("label").alias("a"))).join(labels.select(F.col("id").alias("dst"), F.col("label").alias("b")), "dst")
    open_ = labels.join(ends.where("a <> b").select(F.col("a").alias("label")).distinct(), "label", "left_semi").count()
    vertices = labels.count()
    stats = {"n": vertices, "m": g.own_edges().count(), "diameter_lb": hops if not open_ else hops + 1}
    return stats, (vertices - open_) / vertices if vertices else 1.0


def recommend(g: Graph, cores: int, rounds: int = FEW_HOPS) -> Recommendation:
    """Advice from a few rounds of order 1: what is not done by then has more hops than order 1 is good for."""
    stats, finished = sampled_stats(g, rounds)
    return recommend_method(stats, cores, finished)
