"""Min-mapping as set-oriented steps over an edge table and a label table.

A step of order h sends to the ends of each edge, and to all vertices on their pointer chains before the h-th hop, the
smaller of the two labels h hops away. As a minimum distributes, one aggregate over the edges gives every vertex the
least such label of its neighbours, and further aggregates over the vertices carry it up the pointers.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.graph import directed_view, joined_to
from minlabel.session import stored


def init_labels(vertices: DataFrame) -> DataFrame:
    return vertices.select("id", F.col("id").alias("label"))


def lower_labels(labels: DataFrame, candidates: DataFrame) -> DataFrame:
    """Labels, made smaller where a candidate(id, c) is."""
    least = candidates.groupBy("id").agg(F.min("c").alias("c"))
    return labels.join(least, "id", "left").select("id", F.least("label", F.coalesce("c", "label")).alias("label"))


def moved(values: DataFrame, column: str, pointers: DataFrame) -> DataFrame:
    """values with the column replaced by its pointer. Only pointers that move and are pointed at are looked up, so the many vertices below a root meet nobody there; what is left is small late in a run and then broadcast by the adaptive planner."""
    used = values.select(F.col(column).alias("id")).distinct()
    inner = pointers.where("id <> label").join(used, "id", "left_semi").select(F.col("id").alias(column), F.col("label").alias("_to"))
    return values.join(inner, column, "left").withColumn(column, F.coalesce("_to", column)).drop("_to")


def power_labels(labels: DataFrame, h: int) -> DataFrame:
    """id and the label h hops away."""
    if h < 1:
        raise ValueError("h must be at least 1")
    tables, flat = pointer_tables(labels, h)
    return _hops(tables, flat, h)


def pointer_tables(labels: DataFrame, h: int) -> tuple[list[DataFrame], bool]:
    """P[j] = label 2**j hops away, while 2**j <= h; stops, with True, when hopping on changes nothing."""
    tables = [labels.select("id", "label")]
    while 2 ** len(tables) <= h:
        last = tables[-1]
        new = stored(moved(last.select("id", F.col("label").alias("old"), "label"), "label", last).select("id", "old", "label"))
        if new.where("old <> label").isEmpty():
            return tables, True
        tables.append(new.select("id", "label"))
    return tables, False


def _hops(tables: list[DataFrame], flat: bool, h: int) -> DataFrame:
    if flat:
        return tables[-1]
    out, left = tables[-1], h - 2 ** (len(tables) - 1)
    for j in range(len(tables) - 2, -1, -1):
        if left >= 2**j:
            out, left = moved(out, "label", tables[j]), left - 2**j
    return out


def neighbour_minimum(directed: DataFrame, values: DataFrame, *columns: str) -> DataFrame:
    """Of each vertex with an edge: id and the least of its neighbours' values. The edges stay where they are."""
    sent = joined_to(directed, values.select(F.col("id").alias("src"), *columns))
    return sent.groupBy(F.col("dst").alias("id")).agg(*[F.min(c).alias(c) for c in columns])


def step(directed: DataFrame, labels: DataFrame, order: int = 2) -> DataFrame:
    """One iteration: id, label, before (the label it had) and nearest (least label before among the neighbours)."""
    if order < 1:
        raise ValueError("order must be at least 1")
    if order == 1:
        near = neighbour_minimum(directed, labels.withColumn("nearest", F.col("label")), "nearest")
        out = labels.join(near, "id", "left")
        return out.select("id", F.least("label", F.coalesce("nearest", "label")).alias("label"), F.col("label").alias("before"), "nearest")
    tables, flat = pointer_tables(labels, order)
    far = _hops(tables, flat, order).select("id", F.col("label").alias("far"))
    both = labels.join(far, "id")
    near = neighbour_minimum(directed, both.withColumnRenamed("label", "nearest"), "far", "nearest").withColumnRenamed("far", "c")
    met = both.join(near, "id", "left").select("id", "label", "nearest", F.when(F.col("c").isNotNull(), F.least("c", "far")).alias("c"))
    met = stored(met) if order > 2 else met
    lifted = lift_candidates(met.select("id", "c"), tables, flat, order)
    return met.join(lifted, "id", "left").select("id", F.least("label", F.coalesce("c", "label"), F.coalesce("up", "label")).alias("label"), F.col("label").alias("before"), "nearest")


def lift_candidates(candidates: DataFrame, tables: list[DataFrame], flat: bool, order: int) -> DataFrame:
    """id, up: the least candidate of the vertices whose chain meets id before the order-th hop. Doubling: after the table of 2**j hops, 2**(j+1) places of the chains are covered. A candidate that is not below its target cannot lower it."""

    def by(pointers: DataFrame, held: DataFrame) -> DataFrame:
        sent = held.where("c is not null").join(pointers, "id").where("label <> id and c < label")
        return sent.groupBy(F.col("label").alias("id")).agg(F.min("c").alias("c"))

    def merged(held: DataFrame, more: DataFrame) -> DataFrame:
        # A join, as both have each id once. A union of two tables dealt by id counts as dealt by id too, so its aggregate gets no exchange; the adaptive planner may then part the two after all, and an id's rows lie in two partitions.
        return held.join(more.withColumnRenamed("c", "other"), "id", "full").select("id", F.least("c", "other").alias("c"))

    held, span = candidates.where("c is not null"), 1
    for pointers in tables if flat else tables[:-1] if 2 ** (len(tables) - 1) == order else tables:
        if not flat and 2 * span > order:
            break
        held, span = merged(held, by(pointers, held)), 2 * span
        held = stored(held) if len(tables) > 2 else held
    if not flat and span < order:
        held = merged(held, by(_hops(tables, False, order - span) if order - span < span else tables[-1], held))
    return held.select("id", F.col("c").alias("up"))


def apply_min_mapping(edges: DataFrame, labels: DataFrame, order: int = 2) -> DataFrame:
    """Labels after one synchronous application to all edges(src, dst)."""
    return step(directed_view(edges), labels, order).select("id", "label")


# What can be seen of the pointer forest.


def roots(labels: DataFrame) -> DataFrame:
    return labels.where("id = label").select("id")


def tree_heights(labels: DataFrame) -> DataFrame:
    """root and height of each tree, by doubling."""
    at = labels.select("id", "label", F.when(F.col("id") == F.col("label"), 0).otherwise(1).cast("bigint").alias("hops"))
    while True:
        nxt = at.select(F.col("id").alias("label"), F.col("label").alias("to"), F.col("hops").alias("more"))
        new = stored(at.join(nxt, "label").select("id", F.col("to").alias("label"), F.col("label").alias("old"), (F.col("hops") + F.col("more")).alias("hops")))
        at = new.select("id", "label", "hops")
        if new.where("label <> old").isEmpty():
            return at.groupBy(F.col("label").alias("root")).agg(F.max("hops").alias("height"))


def is_star_forest(labels: DataFrame) -> bool:
    return moved(labels.select("id", F.col("label").alias("old"), "label"), "label", labels).where("old <> label").isEmpty()


def height_after(height: int, h: int) -> int:
    """What one step of order h leaves of a tree of that height, at most."""
    return (height + h - 1) // h


def equal_minimum_sets(labels: DataFrame, order: int = 1, members: bool = False) -> DataFrame:
    at = labels if order == 1 else power_labels(labels, order)
    return at.groupBy("label").agg(F.sort_array(F.collect_set("id")).alias("members") if members else F.count("*").alias("size"))


def merged_minimum_set(labels: DataFrame, order: int = 1) -> DataFrame:
    return (labels if order == 1 else power_labels(labels, order)).select("label").distinct()


def mms_chain_holds(states: list[DataFrame]) -> bool:
    """Labels in use only become fewer: after each round, those of order 2 are among those of order 1, and the next round's among them."""
    before = None
    for labels in states:
        for now in (merged_minimum_set(labels, 1), merged_minimum_set(labels, 2)):
            if before is not None and not now.join(before, "label", "left_anti").isEmpty():
                return False
            before = now
    return True


def root_neighbours(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """Pairs of trees that an edge joins."""
    at = labels
    while not is_star_forest(at):
        at = stored(moved(at, "label", at))
    a = edges.join(at.select(F.col("id").alias("src"), F.col("label").alias("a")), "src").join(at.select(F.col("id").alias("dst"), F.col("label").alias("b")), "dst")
    return a.where("a <> b").select(F.least("a", "b").alias("root_a"), F.greatest("a", "b").alias("root_b")).distinct()
