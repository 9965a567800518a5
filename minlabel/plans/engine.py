"""connected_components: the loop over immutable tables, one plan for each iteration.

The variants update labels in place by default. Blocks of edges are swept in memory, part after part, so labels spread
within a round; a block hands on a thinner set of edges that connects the same, each from an id to a smaller one. One
exchange by id then gives every id its least neighbour, its pointer, and joins the others to that, so an id that nothing
points at is done with: it is left out of the next round, and takes its pointer's label in the end. Pointers that go on
are followed as many hops as the order says. No edge is left when labels have converged, so the early check costs nothing,
and finished components drop out by themselves. The first round exchanges only the thinned edges, however large a hub is;
later ones are on what is left.

update="sync" keeps to rounds that all read the labels from before them, on edges that never move; sync2 and order1 do so.
update="block_async" sends the labels of its ends to each block of edges and sweeps it there, without contraction.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from minlabel import schemas
from minlabel.graph import Graph, dealt, hubs_of, joined_to
from minlabel.operators import kernels, mapping
from minlabel.plans.schedules import HIGH, schedule
from minlabel.session import Scratch, checkpoint, collect_stored, discard, discard_collected, stored

#: Options that only synchronous rounds have.
SYNCHRONOUS = {"applications", "early_check", "retire", "contract_after", "store"}
SCHEDULED = ("sync2", "order1", "order2", "orderm", "low_then_high", "alternate", "schedule")
BASELINES = ("hook_compress", "hook_compress_classic", "union_find", "bfs", "label_propagation")
UPDATES = ("in_place", "sync", "chained", "block_async")
METHODS = (*SCHEDULED, "block_async", "chained", *BASELINES)


class NotConverged(RuntimeError):
    pass


@dataclass
class ComponentResult:
    labels: DataFrame
    method: str
    iterations: int
    edge_passes: int
    converged: bool = True
    trace: list[tuple] = field(default_factory=list)

    def trace_table(self) -> DataFrame:
        return self.labels.sparkSession.createDataFrame(self.trace, schemas.TRACE)


@dataclass
class Options:
    order: int = HIGH
    orders: object = None
    warmup: int = 2
    applications: int = 1
    update: str = "in_place"
    local_sweeps: int | None = None  # of a block's edges in a round; 0: until the block is settled; None: one, but for the last block, which is settled
    block_edges: int = kernels.BLOCK_EDGES
    blocks: int | None = None
    early_check: str = "fused"  # eager scans the edges once more each round, fused finds out one scan late
    retire: bool = False
    contract_after: int | None = None
    max_iterations: int = 200
    num_partitions: int | None = None
    fan_in: int = 8
    max_kernel_ids: int = 50_000_000
    store: object = None
    local_edges: int = 0  # synchronous rounds of orders 1 and 2, and of hook_compress, of a graph of at most so many edges are made in one task; in-place rounds follow at most so many pointers in one task
    atomic: bool = False  # there are no races to guard against: a minimum may be taken in any order, and again

    def __post_init__(self):
        if self.early_check not in ("off", "fused", "eager"):
            raise ValueError(f"early_check is off, fused or eager, not {self.early_check}")
        if self.update not in UPDATES:
            raise ValueError(f"update is one of {UPDATES}, not {self.update}")
        if self.applications not in (1, 2) or self.max_iterations < 1:
            raise ValueError("applications is 1 or 2, max_iterations at least 1")
        if (self.local_sweeps or 0) < 0 or self.block_edges < 1:
            raise ValueError("local_sweeps is at least 0, block_edges at least 1")


def connected_components(graph: Graph, method: str = "order2", **options) -> ComponentResult:
    """The smallest id of its component for each vertex.

    method: one of METHODS. order1 spreads labels by one edge a round, order2 (the default) follows pointers two deep,
    orderm many; low_then_high and alternate mix them; sync2 is order2 without the early check; block_async settles
    blocks of edges in memory; the rest are baselines."""
    if method not in METHODS:
        raise ValueError(f"no method {method}")
    opts = _checked(method, options)
    n = opts.num_partitions or int(graph.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if method in BASELINES:
        from minlabel.plans import baselines

        return getattr(baselines, method)(graph, opts, n)
    orders = schedule("order2" if method in ("block_async", "chained") else method, opts.order, opts.warmup, opts.orders)
    return (_run_in_place if opts.update == "in_place" else _run)(graph, method, orders, opts, n)


def _checked(method: str, options: dict) -> Options:
    """The options, with what the method settles; an error where they contradict it or each other."""
    given = dict(options)
    synchronous = SYNCHRONOUS & set(given)
    if given.get("orders") is not None and method != "schedule":
        raise ValueError(f"orders are for a schedule, not for {method}")
    if "order" in given and method not in ("orderm", "low_then_high", "alternate"):
        raise ValueError(f"{method} has no order of its own to choose")
    if method in ("block_async", "chained"):
        if given.setdefault("update", method) != method:
            raise ValueError(f"{method} is an update of its own")
    elif method in ("sync2", "order1"):
        given.setdefault("update", "sync")
        if method == "sync2" and given["update"] != "sync":
            raise ValueError("sync2 is synchronous")
        if method == "sync2":
            given.setdefault("early_check", "off")
    elif synchronous:
        given.setdefault("update", "sync")
    opts = Options(**given)
    if method not in BASELINES and opts.update == "in_place" and synchronous:
        raise ValueError(f"in-place rounds have no {', '.join(sorted(synchronous))}")
    return opts


def unsettled(directed: DataFrame, labels: DataFrame) -> DataFrame:
    """Vertices with a neighbour of a smaller label. If there is none, no edge joins two labels, and all is done: the labels of a component are then one of its ids that is at most each of them."""
    near = mapping.neighbour_minimum(directed, labels.withColumnRenamed("label", "nearest"), "nearest")
    return labels.join(near, "id").where("nearest < label")


def settled(directed: DataFrame, labels: DataFrame) -> bool:
    return unsettled(directed, labels).isEmpty()


ROUNDS = "id bigint, label bigint, k int, changed bigint, open bigint, seconds double"


def in_one_task(graph: Graph, opts: Options, step, early: bool) -> tuple[DataFrame, list] | None:
    """Labels and (k, changed, open, seconds) of each round, in order, if the graph is small enough that all its rounds are made in one task."""
    if not opts.local_edges or not 0 < graph.own_edges().count() <= opts.local_edges:
        return None
    out = stored(graph.own_edges().coalesce(1).mapInArrow(kernels.rounds_kernel(step, opts.max_iterations, early), ROUNDS), "rounds")
    rounds = sorted(out.where("id is null").select("k", "changed", "open", "seconds").collect(), key=lambda r: r.k or opts.max_iterations + 1)
    labels = graph.vertices.join(out.where("id is not null").select("id", "label"), "id", "left").select("id", F.coalesce("label", "id").alias("label"))
    return labels, rounds


def _synchronous_in_one_task(graph: Graph, method: str, orders, opts: Options) -> ComponentResult | None:
    if opts.update != "sync" or opts.early_check == "eager" or opts.applications > 1 or opts.retire or opts.contract_after or opts.store is not None:
        return None
    held = [orders(k) for k in range(1, opts.max_iterations + 1)]
    if max(held) > 2:
        return None
    early = opts.early_check == "fused"
    if (made := in_one_task(graph, opts, lambda labels, src, dst, k: kernels.round_of_order(labels, src, dst, held[k - 1]), early)) is None:
        return None
    labels, rounds = made
    edge_rows = 2 * graph.own_edges().count()
    trace = [(graph.name, method, r.k, held[r.k - 1], r.changed, r.open if early else None, edge_rows, r.seconds) for r in rounds if r.k]
    return ComponentResult(labels, method, len(trace), len(rounds), True, trace)


def _run(graph: Graph, method: str, orders, opts: Options, n: int) -> ComponentResult:
    if (local := _synchronous_in_one_task(graph, method, orders, opts)) is not None:
        return local
    directed = graph.prepared(n)
    edge_rows = directed.count()
    labels = stored(mapping.init_labels(graph.vertices))
    k, passes, trace, sliced, last = 0, 0, [], None, None
    if opts.store is not None and (kept := opts.store.latest(graph.edges.sparkSession)):
        k, labels = kept[0], kept[1]
    while edge_rows:
        if k >= opts.max_iterations:
            raise NotConverged(f"{method} is not done after {k} iterations")
        k, began = k + 1, time.perf_counter()
        h = orders(k)
        state = labels
        if opts.update == "block_async" and sliced is None:
            sliced = _edge_blocks(graph, opts.blocks or n, opts.block_edges)
        made = collect_stored()
        if opts.update == "block_async":
            out = _block_round(*sliced, labels, h, opts.local_sweeps or 0)
            passes += 1
        elif opts.update == "chained":
            parts = opts.blocks or 4
            if sliced is None:  # the slice is a stored column: a long condition would be inferred again at every join
                sliced = dealt(directed.withColumn("slice", F.pmod(F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst")), F.lit(parts)).cast("int")), n, hubs_of(directed))
            for b in range(parts):
                own = sliced.where(F.col("slice") == b)
                own._hubs = hubs_of(directed)
                state = stored(mapping.step(own, state, h).select("id", "label"))
            out = stored(state.join(labels.withColumnRenamed("label", "before"), "id").select("id", "label", "before", F.lit(None).cast("bigint").alias("nearest")))
            passes += 1
        else:
            for _ in range(opts.applications):
                out = stored(mapping.step(directed, state, h))
                state = out.select("id", "label")
                passes += 1
        seen = out.agg(F.count_if(F.expr("label < before")).alias("changed"), F.count_if(F.expr("nearest < before")).alias("open")).first()
        discard_collected(made, out)
        old, labels = last, out.select("id", "label")
        last = out
        if old is not None:
            discard(old)
        done, violations = seen.changed == 0, None
        if opts.early_check == "fused" and opts.update == "sync" and opts.applications == 1:
            if not seen.open:  # the labels were final before this round, which therefore does not count
                k -= 1
                break
            done, violations = False, seen.open  # of the state before
        elif opts.early_check != "off" and not done:
            passes += 1
            done = settled(directed, labels)
            violations = 0 if done else None
        if opts.store is not None:
            opts.store.save(k, labels)
        trace.append((graph.name, method, k, h, seen.changed, violations, edge_rows, time.perf_counter() - began))
        if done:
            break
        if opts.retire:
            directed, edge_rows = _active(directed, labels, n)
        if opts.contract_after and k >= opts.contract_after:
            return _contracted(graph, directed, labels, method, opts, k, passes, trace)
    return ComponentResult(labels, method, k, passes, True, trace)


def _active(directed: DataFrame, labels: DataFrame, n: int) -> tuple[DataFrame, int]:
    """Edges of components that are not finished: a label that no edge leaves is a whole component."""
    both = joined_to(directed, labels.select(F.col("id").alias("src"), F.col("label").alias("c"))).groupBy(F.col("dst").alias("id")).agg(F.min("c").alias("low"), F.max("c").alias("high"))
    names = labels.join(both, "id").where("low < label or high > label").select("label").distinct()
    keep = labels.join(names, "label", "left_semi").select(F.col("id").alias("src"))
    left = dealt(joined_to(directed, keep), n, hubs_of(directed))
    return left, left.count()


def contracted_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The graph of the labels: ends replaced by their labels, without loops and repetitions. Labels are frozen here, so dropping edges within a label is safe; between rounds it would not be."""
    ends = edges.join(labels.select(F.col("id").alias("src"), F.col("label").alias("a")), "src").join(labels.select(F.col("id").alias("dst"), F.col("label").alias("b")), "dst")
    return ends.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).where("src < dst").distinct()


def composed(labels: DataFrame, over: DataFrame) -> DataFrame:
    """Labels replaced by their labels in the graph over them."""
    return mapping.moved(labels, "label", over)


def _contracted(graph, directed, labels, method, opts, k, passes, trace):
    edges = stored(contracted_edges(directed.where("src < dst"), labels))
    inner = connected_components(Graph(edges, labels.select(F.col("label").alias("id")).distinct(), graph.name), "order2", max_iterations=opts.max_iterations)
    return ComponentResult(stored(composed(labels, inner.labels)), method, k + inner.iterations, passes + inner.edge_passes, True, trace + inner.trace)


def _edge_blocks(graph: Graph, blocks: int, most: int) -> tuple[DataFrame, DataFrame]:
    """Edges in blocks of about most at most, whatever their ends' degrees, and the ends of each block."""
    edges = graph.own_edges()
    blocks = max(blocks, -(-edges.count() // most))
    dealt = stored(edges.repartitionByRange(blocks, "src", "dst").select(F.spark_partition_id().alias("block"), "src", "dst"), "blocks")
    return dealt, stored(dealt.select("block", F.explode(F.array("src", "dst")).alias("id")).distinct(), "ends")


def _block_round(edges: DataFrame, ends: DataFrame, labels: DataFrame, order: int, sweeps: int) -> DataFrame:
    """Labels, and their labels, are sent to the blocks that their ids are in; each block is swept in memory; one minimum over the blocks."""
    far = mapping.moved(labels.select("id", "label", F.col("label").alias("far")), "far", labels)
    sent = ends.join(far, "id").select("block", "id", "label", "far")
    low = edges.groupBy("block").cogroup(sent.groupBy("block")).applyInArrow(kernels.cogrouped_kernel(order, sweeps), "id bigint, label bigint").groupBy("id").agg(F.min("label").alias("c"))
    least = far.select("id", "label", F.least("label", "far").alias("far")).join(low, "id", "left")
    return stored(least.select("id", F.least("far", F.coalesce("c", "far")).alias("label"), F.col("label").alias("before"), F.lit(None).cast("bigint").alias("nearest")))


def _least_neighbours(edges: DataFrame, order: int, sweeps: int, block: int) -> DataFrame:
    """One in-place round: id, to (its least neighbour below), goes_on (other ids point at it), each once, and beside them the edges a-b of the next round."""
    rows = edges.mapInArrow(kernels.thinning_kernel(order, sweeps, block), "id bigint, down bigint")
    own, sorted_ = Window.partitionBy("id"), Window.partitionBy("id").orderBy(F.asc_nulls_last("down"))
    seen = rows.select("id", "down", F.min("down").over(own).alias("to"), F.max(F.col("down").isNull()).over(own).alias("on"), F.row_number().over(sorted_).alias("k"), F.lag("down").over(sorted_).alias("last"))
    first, other = F.col("k") == 1, (F.col("down") > F.col("to")) & (F.col("down") < F.col("id")) & ~F.col("down").eqNullSafe(F.col("last"))
    kept = seen.where(F.col("to").isNotNull() & (first | other))
    edge = other | (F.col("on") & (F.col("to") < F.col("id")))
    return kept.select(F.when(first, F.col("id")).alias("id"), F.when(first, F.col("to")).alias("to"), (F.col("on") & (F.col("to") < F.col("id"))).alias("goes_on"), F.when(edge, F.when(first, F.col("id")).otherwise(F.col("down"))).alias("a"), F.when(edge, F.col("to")).alias("b"))


def _followed(step: DataFrame, order: int, scratch: Scratch, local: bool) -> DataFrame:
    """Edges of the next round, with the pointers that go on followed order hops: a tree that is order deep then hangs together in one round. local: in one task."""
    pointers, doublings = step.where("id is not null"), order.bit_length() - 1
    moving = pointers.where("goes_on").select("id", F.col("to").alias("label"))
    if local:
        moving, doublings = moving.coalesce(1).mapInArrow(kernels.pointers_kernel(doublings), "id bigint, label bigint"), 0
    moving = scratch.stored(moving, "pointers")
    for _ in range(doublings):
        new = scratch.stored(mapping.moved(moving.select("id", F.col("label").alias("old"), "label"), "label", moving).select("id", "old", "label"), "pointers")
        done = new.where("old <> label").isEmpty()
        moving = new.select("id", "label")
        if done:
            break
    return step.where("id is null").select("a", "b").unionByName(moving.select(F.col("id").alias("a"), F.col("label").alias("b")))


def _run_in_place(graph: Graph, method: str, orders, opts: Options, n: int) -> ComponentResult:
    edges = graph.raw if graph.raw is not None else graph.edges
    scratch, steps, trace, k, edge_rows, finished = Scratch(), [], [], 0, None, 0
    while edge_rows != 0:
        if k >= opts.max_iterations:
            scratch.clear()
            raise NotConverged(f"{method} is not done after {k} iterations")
        k, began = k + 1, time.perf_counter()
        h, last_block = orders(k), edge_rows is not None and edge_rows <= opts.block_edges
        seen = Observation()
        sweeps = opts.local_sweeps if opts.local_sweeps is not None else 0 if last_block else 1
        step = _least_neighbours(edges.coalesce(1) if last_block else edges, h, sweeps, opts.block_edges)
        step = scratch.stored(step.observe(seen, F.count_if(F.expr("to < id")).alias("changed"), F.count("a").alias("left"), F.count_if(F.expr("id is not null and not goes_on")).alias("finished")), "step")
        changed, left = seen.get["changed"], seen.get["left"]
        steps.append(step)
        finished += seen.get["finished"]
        if not changed:  # no edge joins two vertices
            k -= 1
            break
        trace.append((graph.name, method, k, h, changed, left, edge_rows, time.perf_counter() - began))
        edge_rows = left
        follow = left and h > 1 and (left > opts.block_edges or opts.local_sweeps)  # a block that is settled next follows by itself
        edges = _followed(step, h, scratch, left <= opts.local_edges) if follow else step.where("a is not null").select("a", "b")
    labels = _composed_steps(steps, scratch, finished <= opts.local_edges and graph.given is None)
    if graph.given is not None:
        more = graph.given.select("id", F.col("id").alias("label")).unionByName(labels.select(F.col("label").alias("id"), "label"))
        labels = labels.unionByName(more).groupBy("id").agg(F.min("label").alias("label"))
    else:
        labels = graph.vertices.join(labels, "id", "left").select("id", F.coalesce("label", "id").alias("label"))
    out = stored(labels)
    scratch.clear()
    return ComponentResult(out, method, k, k, True, trace)


def _composed_steps(steps: list[DataFrame], scratch: Scratch, local: bool) -> DataFrame:
    """id and label of all ids with a smaller one in their component: those that were done with in each round take the label of their pointer, from the last round to the first. Each is done with once, so all rounds together move each id twice at most. local: in one task, if no id has a loop."""
    if local:
        held = [s.where("id is not null and not goes_on").select("id", F.col("to").alias("label")) for s in steps]
        return reduce(DataFrame.unionByName, held).coalesce(1).mapInArrow(kernels.pointers_kernel(64), "id bigint, label bigint")
    known = None
    for k in range(len(steps) - 1, -1, -1):
        done = steps[k].where("id is not null and not goes_on").select("id", F.col("to").alias("label"))
        if known is not None:
            over = known.select(F.col("id").alias("label"), F.col("label").alias("least"))
            done = done.join(over, "label", "left").select("id", F.coalesce("least", "label").alias("label")).unionByName(known)
        known = scratch.stored(done) if 0 < k < len(steps) - 1 else done
    return known
