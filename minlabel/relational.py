"""Relational, window, set and scalar operators over the given tables, each a query with its SQL."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from minlabel.session import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
#: Users of a block of session_overlap_all_users, whose pairs with another block's are counted in one task.
WIDE = 4096


def registrar(queries: dict, oracles: dict[str, str]):
    """A decorator that keeps a query by its name, with its SQL if there is one."""

    def query(sql: str | None = None):
        def keep(f):
            queries[f.__name__] = f
            if sql:
                oracles[f.__name__] = sql
            return f

        return keep

    return query


query = registrar(QUERIES, ORACLES)


def _t(spark: SparkSession, d: str, *names: str):
    out = [table(spark, d, n) for n in names]
    return out[0] if len(out) == 1 else out


@query("select l_orderkey, l_partkey from lineitem where l_quantity > 45 and l_returnflag = 'R'")
def scan_lineitem_pruned(spark, d):
    return _t(spark, d, "lineitem").where("l_quantity > 45 and l_returnflag = 'R'").select("l_orderkey", "l_partkey")


@query("select count(*) as edges, count(distinct src) as left_ends, min(src) as low, max(dst) as high from (select distinct l_orderkey * 2 as src, l_partkey * 2 + 1 as dst from lineitem)")
def canonical_edges_order_part(spark, d):
    from minlabel.graph import canonical_edges, tagged

    e = canonical_edges(_t(spark, d, "lineitem").select(tagged("l_orderkey", 0).alias("src"), tagged("l_partkey", 1).alias("dst")))
    # the tagged order is kept by the pairs' numbers, so ends are put back by tag
    left = F.when(F.col("src") % 2 == 0, F.col("src")).otherwise(F.col("dst"))
    right = F.when(F.col("src") % 2 == 1, F.col("src")).otherwise(F.col("dst"))
    return e.agg(F.count("*").alias("edges"), F.countDistinct(left).alias("left_ends"), F.min(left).alias("low"), F.max(right).alias("high"))


@query("select src, count(*) as n from (select o_custkey * 2 as src from orders union all select o_orderkey * 2 + 1 from orders) group by src")
def directed_view_counts(spark, d):
    from minlabel.graph import directed_view
    from minlabel.workloads import customer_order

    return directed_view(customer_order(spark, d).edges).groupBy("src").agg(F.count("*").alias("n"))


@query("select p_partkey from part where p_size between 10 and 20 and p_brand in ('Brand#1', 'Brand#2', 'Brand#11', 'Brand#12') and p_name like '%a%' and p_type is not null")
def filter_predicates(spark, d):
    return _t(spark, d, "part").where(F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#11", "Brand#12") & F.col("p_name").like("%a%") & F.col("p_type").isNotNull()).select("p_partkey")


@query("select c_custkey, case when c_acctbal < 0 then 'debt' when c_acctbal < 1000 then 'low' else 'high' end as class, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') as segment, cast(floor(c_acctbal) as bigint) as whole from customer")
def project_exprs(spark, d):
    c = _t(spark, d, "customer")
    return c.select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 1000, "low").otherwise("high").alias("class"), F.coalesce(F.nullif(F.col("c_mktsegment"), F.lit("BUILDING")), F.lit("none")).alias("segment"), F.floor("c_acctbal").cast("bigint").alias("whole"))


@query("select o_orderkey, c_nationkey from orders join customer on o_custkey = c_custkey where o_totalprice > 1000")
def join_orders_customers(spark, d):
    o, c = _t(spark, d, "orders", "customer")
    return o.where("o_totalprice > 1000").hint("shuffle_hash").join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")


@query("select c_custkey, n_name from customer join nation on c_nationkey = n_nationkey")
def join_broadcast_nation(spark, d):
    c, n = _t(spark, d, "customer", "nation")  # nations have a fixed number
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@query("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)")
def anti_unordered_customers(spark, d):
    c, o = _t(spark, d, "customer", "orders")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("select p_partkey from part where p_partkey in (select l_partkey from lineitem where l_quantity > 49)")
def semi_active_parts(spark, d):
    p, lines = _t(spark, d, "part", "lineitem")
    return p.join(lines.where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@query("select coalesce(a.k, b.k) as k, a.n as customers, b.n as suppliers from (select c_nationkey as k, count(*) as n from customer where c_acctbal > 5000 group by 1) a full join (select s_nationkey as k, count(*) as n from supplier where s_acctbal > 5000 group by 1) b on a.k = b.k")
def full_outer_nations(spark, d):
    c, s = _t(spark, d, "customer", "supplier")
    a = c.where("c_acctbal > 5000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    b = s.where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "k", "full")


@query("select a.n_nationkey as a, b.n_nationkey as b from nation a join nation b on a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")
def self_join_nations(spark, d):
    n = _t(spark, d, "nation")
    a, b = n.select(F.col("n_nationkey").alias("a"), "n_regionkey"), n.select(F.col("n_nationkey").alias("b"), "n_regionkey")
    return a.join(b, "n_regionkey").where("a < b").select("a", "b")


@query("select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_acctbal < b.s_acctbal and b.s_acctbal < a.s_acctbal + 100")
def theta_acctbal_pairs(spark, d):
    return range_pairs(_t(spark, d, "supplier").select("s_suppkey", "s_acctbal"), "s_suppkey", F.col("s_acctbal"), 100.0).select("a", "b")


def range_pairs(df: DataFrame, id: str, value: Column, width: float) -> DataFrame:
    """Pairs a, b with a's value < b's < a's + width: each value goes to its bin, and as a left side to the next one too, so that the join is by bin."""
    rows = df.select(F.col(id).alias("id"), value.alias("v")).withColumn("bin", F.floor(F.col("v") / width))
    left = rows.select(F.col("id").alias("a"), F.col("v").alias("va"), F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    right = rows.select(F.col("id").alias("b"), F.col("v").alias("vb"), "bin")
    return left.join(right, "bin").where((F.col("va") < F.col("vb")) & (F.col("vb") < F.col("va") + width))


@query("select a.event_id as a, count(*) as n from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval '2 hours' group by 1")
def range_events_window(spark, d):
    e = _t(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    width = 2 * 3600 * 1_000_000
    left = e.select(F.col("event_id").alias("a"), "user_id", F.col("us").alias("ua"), F.explode(F.array(F.expr(f"us div {width}"), F.expr(f"us div {width} + 1"))).alias("bin"))
    right = e.select("user_id", F.col("us").alias("ub"), F.expr(f"us div {width}").alias("bin"))
    return left.join(right, ["user_id", "bin"]).where(f"ub > ua and ub <= ua + {width}").groupBy("a").agg(F.count("*").alias("n"))


@query("select o_orderkey, e.event_id from (select o_orderkey, o_custkey % 150 as u, cast(o_orderdate as timestamp) as ts from orders) o asof join (select event_id, user_id, ts from events) e on o.u = e.user_id and o.ts >= e.ts")
def asof_previous_event(spark, d):
    """The last event of the order's user up to the order's time: one union and one window, no join."""
    o, e = _t(spark, d, "orders", "events")
    left = o.select((F.col("o_custkey") % 150).alias("u"), F.col("o_orderdate").alias("ts"), F.lit(1).alias("side"), F.col("o_orderkey"), F.lit(None).cast("bigint").alias("event_id"))
    right = e.select(F.col("user_id").alias("u"), "ts", F.lit(0).alias("side"), F.lit(None).cast("bigint").alias("o_orderkey"), "event_id")
    w = Window.partitionBy("u").orderBy("ts", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return left.unionByName(right).withColumn("event_id", F.last("event_id", True).over(w)).where("side = 1 and event_id is not null").select("o_orderkey", "event_id")


_SESSIONS = "select user_id, min(epoch_us(ts)) as a, max(epoch_us(ts)) as b from (select *, sum(f) over (partition by user_id order by ts, event_id) as n from (select *, case when ts <= lag(ts) over (partition by user_id order by ts, event_id) + interval '6 hours' then 0 else 1 end as f from events)) group by user_id, n"


@query(f"select x.user_id as u, y.user_id as v, count(*) as n from ({_SESSIONS}) x join ({_SESSIONS}) y on x.user_id < y.user_id and y.user_id < x.user_id + 3 and x.a <= y.b and y.a <= x.b group by 1, 2")
def interval_session_overlap(spark, d):
    """Sessions of neighbouring users that overlap: intervals are spread over day bins, joined by bin, and counted once, in the bin where the overlap begins."""
    s = sessions(_t(spark, d, "events"))
    day = 86_400_000_000
    spread = s.select("user_id", "a", "b", F.explode(F.sequence(F.expr(f"a div {day}"), F.expr(f"b div {day}"))).alias("bin"))
    left = spread.select("bin", "a", "b", F.col("user_id").alias("u"), F.explode(F.array(F.col("user_id") + 1, F.col("user_id") + 2)).alias("v"))
    right = spread.select("bin", F.col("user_id").alias("v"), F.col("a").alias("a2"), F.col("b").alias("b2"))
    return left.join(right, ["bin", "v"]).where("a <= b2 and a2 <= b").where(f"bin = greatest(a, a2) div {day}").groupBy("u", "v").agg(F.count("*").alias("n"))


@query(f"select x.user_id as u, y.user_id as v, count(*) as n from ({_SESSIONS}) x join ({_SESSIONS}) y on x.user_id < y.user_id and x.a <= y.b and y.a <= x.b group by 1, 2")
def session_overlap_all_users(spark, d):
    """As interval_session_overlap, for all pairs of users. Each pair of blocks of users counts its own pairs, so sessions are sent to as many groups as there are blocks, and no pair is sent at all."""
    s = sessions(_t(spark, d, "events")).where("user_id is not null and a is not null")
    users = s.agg(F.countDistinct("user_id")).first()[0]
    blocks = max(1, -(-users // WIDE), math.isqrt(2 * int(spark.conf.get("spark.sql.shuffle.partitions"))))
    own = s.withColumn("block", F.pmod(F.xxhash64("user_id"), F.lit(blocks)).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    sent = own.withColumn("other", other).select(F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "user_id", "a", "b")
    return sent.groupBy("i", "j").applyInArrow(_overlaps, "u bigint, v bigint, n bigint")


def _overlaps(rows: pa.Table) -> pa.Table:
    """Numbers of overlapping sessions of the users of one block with those of another, or with each other."""
    block, user, a, b = (rows.column(c).to_numpy() for c in ("block", "user_id", "a", "b"))
    order = np.argsort(a, kind="stable")
    block, user, a, b = block[order], user[order], a[order], b[order]
    i, j = rows.column("i")[0].as_py(), rows.column("j")[0].as_py()
    left, right = (np.flatnonzero(block == k) for k in (i, j))
    (us, x), (vs, y) = (np.unique(user[k], return_inverse=True) for k in (left, right))
    counts = np.zeros((len(us), len(vs)), np.int32)
    if i == j:
        _count(counts, x, x, np.arange(1, len(x) + 1), np.searchsorted(a[left], b[left], "right"))
        counts = np.triu(counts + counts.T, 1)  # a user's own sessions are apart
    else:  # the later one of two sessions begins within the other
        _count(counts, x, y, np.searchsorted(a[right], a[left]), np.searchsorted(a[right], b[left], "right"))
        _count(counts.T, y, x, np.searchsorted(a[left], a[right], "right"), np.searchsorted(a[left], b[right], "right"))
    out, wide = [], max(1, (1 << 18) // max(1, len(vs)))
    for k in range(0, len(us), wide):
        p, q = np.nonzero(counts[k : k + wide])
        u, v = us[p + k], vs[q]
        out.append(pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (np.minimum(u, v), np.maximum(u, v), counts[p + k, q])], names=["u", "v", "n"]))
    return pa.Table.from_batches(out, pa.schema([(c, pa.int64()) for c in ("u", "v", "n")]))


def _count(counts: np.ndarray, x: np.ndarray, y: np.ndarray, begin: np.ndarray, end: np.ndarray, most: int = 1 << 20) -> None:
    """One more for (x[k], y[l]) for each l from begin[k] to end[k], some at a time."""
    edge = np.concatenate(([0], np.cumsum(np.maximum(end - begin, 0))))
    for lo in range(0, int(edge[-1]), most):
        place = np.arange(lo, min(lo + most, int(edge[-1])))
        k = np.searchsorted(edge, place, "right") - 1
        np.add.at(counts, (x[k], y[begin[k] + place - edge[k]]), 1)


def sessions(events: DataFrame, hours: int = 6) -> DataFrame:
    """user_id, a, b (microseconds) of sessions: gaps and islands."""
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    e = events.select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    new = F.when(F.col("us") <= F.lag("us").over(w) + hours * 3_600_000_000, 0).otherwise(1)
    return e.withColumn("new", new).withColumn("n", F.sum("new").over(w)).groupBy("user_id", "n").agg(F.min("us").alias("a"), F.max("us").alias("b"))


@query(f"select user_id, count(*) as n from ({_SESSIONS}) group by 1")
def sessions_islands(spark, d):
    return sessions(_t(spark, d, "events")).groupBy("user_id").agg(F.count("*").alias("n"))


def heavy_key_join(left: DataFrame, right: DataFrame, key: str, heavy: int, most: int = 1000) -> DataFrame:
    """Inner join in which keys with over heavy rows on the left are joined by broadcast (most of them at most), the others by shuffling."""
    keys = [r[0] for r in left.groupBy(key).agg(F.count("*").alias("n")).where(F.col("n") > heavy).orderBy(F.desc("n")).limit(most).select(key).collect()]
    if not keys:
        return left.join(right, key)
    hot = F.col(key).isin(keys)
    return left.where(hot).join(F.broadcast(right.where(hot)), key).unionByName(left.where(~hot | F.col(key).isNull()).join(right, key))


@query("select l_orderkey, s_nationkey from lineitem join supplier on l_suppkey = s_suppkey where l_quantity = 1")
def heavy_key_split_join(spark, d):
    lines, s = _t(spark, d, "lineitem", "supplier")
    out = heavy_key_join(lines.where("l_quantity = 1").select("l_orderkey", F.col("l_suppkey").alias("k")), s.select(F.col("s_suppkey").alias("k"), "s_nationkey"), "k", 10)
    return out.select("l_orderkey", "s_nationkey")


@query("select r_name, event_type from region, (select distinct event_type from events)")
def cross_region_type(spark, d):
    """Each region with each kind of event: the kinds, a short list, are one row, and are spread over the regions."""
    r, e = _t(spark, d, "region", "events")
    kinds = e.agg(F.collect_set("event_type").alias("kinds")).withColumn("one", F.lit(1))
    return r.withColumn("one", F.lit(1)).join(F.broadcast(kinds), "one").select("r_name", F.explode("kinds").alias("event_type"))


@query("select lang, min(text) as first_text, max(length(text)) as longest from documents group by lang")
def min_text_per_lang(spark, d):
    return _t(spark, d, "documents").groupBy("lang").agg(F.min("text").alias("first_text"), F.max(F.length("text")).cast("bigint").alias("longest"))


@query("select l_suppkey, count(distinct l_partkey) as parts from lineitem group by 1")
def component_distinct_parts(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"))


@query()
def approx_distinct_parts(spark, d):
    return _t(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("select o_orderstatus, o_orderpriority, count(*) as n, grouping(o_orderstatus) * 2 + grouping(o_orderpriority) as g from orders group by rollup (o_orderstatus, o_orderpriority)")
def rollup_orders(spark, d):
    return _t(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("g"))


@query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube (o_orderstatus, o_orderpriority)")
def cube_orders(spark, d):
    return _t(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def grouping_sets_orders(spark, d):
    _t(spark, d, "orders").createOrReplaceTempView("ml_orders")
    return spark.sql("select o_orderstatus, o_orderpriority, count(*) as n from ml_orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")


@query("select event_type, count(*) as n, count(*) filter (where value > 50) as large, bool_or(value > 99) as any_top, bool_and(value >= 0) as none_below, min(value) as low, max(value) as high from events group by 1")
def agg_suite(spark, d):
    return _t(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("large"), F.bool_or(F.col("value") > 99).alias("any_top"), F.bool_and(F.col("value") >= 0).alias("none_below"), F.min("value").alias("low"), F.max("value").alias("high"))


@query("select cast(quantile_cont(n, 0.5) as double) as median, cast(quantile_cont(n, 0.9) as double) as p90 from (select l_partkey, count(*) as n from lineitem group by 1)")
def degree_percentiles(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).agg(F.percentile("n", 0.5).alias("median"), F.percentile("n", 0.9).alias("p90"))


@query("select r_regionkey, string_agg(cast(n_nationkey as varchar), ',' order by n_nationkey) as members, min_by(n_name, n_nationkey) as first_name, max_by(n_name, n_nationkey) as last_name from region join nation on r_regionkey = n_regionkey group by 1")
def ems_members(spark, d):
    r, n = _t(spark, d, "region", "nation")
    return r.join(n, F.col("r_regionkey") == F.col("n_regionkey")).groupBy("r_regionkey").agg(F.array_join(F.transform(F.sort_array(F.collect_set("n_nationkey")), lambda x: x.cast("string")), ",").alias("members"), F.min_by("n_name", "n_nationkey").alias("first_name"), F.max_by("n_name", "n_nationkey").alias("last_name"))


@query("select user_id, count(*) filter (where event_type = 'click') as click, count(*) filter (where event_type = 'view') as view from events group by 1")
def pivot_event_types(spark, d):
    return _t(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)


@query("select c_custkey, 'nation' as name, cast(c_nationkey as bigint) as value from customer union all select c_custkey, 'balance', cast(floor(c_acctbal) as bigint) from customer")
def unpivot_customers(spark, d):
    c = _t(spark, d, "customer").select("c_custkey", F.col("c_nationkey").cast("bigint").alias("nation"), F.floor("c_acctbal").cast("bigint").alias("balance"))
    return c.unpivot("c_custkey", ["nation", "balance"], "name", "value")


@query("select o_orderkey, row_number() over w as rn, rank() over w as r, dense_rank() over w as dr, ntile(4) over w as q from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey)")
def window_ranking(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    n = lambda c, name: c.over(w).cast("bigint").alias(name)
    return _t(spark, d, "orders").select("o_orderkey", n(F.row_number(), "rn"), n(F.rank(), "r"), n(F.dense_rank(), "dr"), n(F.ntile(4), "q"))


@query("select event_id, lag(event_id) over w as before, lead(event_id) over w as after, first_value(event_id) over w as first_id, nth_value(event_id, 2) over w as second from events window w as (partition by user_id order by ts, event_id)")
def window_analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _t(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(w).alias("second"))


@query("select event_id, count(*) over (partition by user_id order by ts, event_id rows between 2 preceding and current row) as last3, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as day from events")
def window_frames(spark, d):
    e = _t(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    span = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(rows).alias("last3"), F.count("*").over(span).alias("day"))


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 50 offset 10")
def sort_limit_orders(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(50)


@query("select l_suppkey, l_partkey, n from (select l_suppkey, l_partkey, count(*) as n, row_number() over (partition by l_suppkey order by count(*) desc, l_partkey) as k from lineitem group by 1, 2) where k <= 3")
def topk_per_component(spark, d):
    n = _t(spark, d, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.count("*").alias("n"))
    return n.withColumn("k", F.row_number().over(Window.partitionBy("l_suppkey").orderBy(F.desc("n"), "l_partkey"))).where("k <= 3").drop("k")


@query("select c_nationkey as k from customer where c_acctbal > 9000 union select s_nationkey from supplier where s_acctbal > 9000")
def setops_union(spark, d):
    c, s = _t(spark, d, "customer", "supplier")
    return c.where("c_acctbal > 9000").select(F.col("c_nationkey").alias("k")).unionByName(s.where("s_acctbal > 9000").select(F.col("s_nationkey").alias("k"))).distinct()


@query("select l_partkey as k from lineitem where l_quantity < 10 intersect all select l_partkey from lineitem where l_quantity > 40")
def setops_intersect_all(spark, d):
    lines = _t(spark, d, "lineitem")
    return lines.where("l_quantity < 10").select(F.col("l_partkey").alias("k")).intersectAll(lines.where("l_quantity > 40").select(F.col("l_partkey").alias("k")))


@query("select l_partkey as k from lineitem where l_quantity < 10 except all select l_partkey from lineitem where l_quantity > 40")
def setops_except_all(spark, d):
    lines = _t(spark, d, "lineitem")
    return lines.where("l_quantity < 10").select(F.col("l_partkey").alias("k")).exceptAll(lines.where("l_quantity > 40").select(F.col("l_partkey").alias("k")))


@query()
def sampled_edges(spark, d):
    return _t(spark, d, "lineitem").select("l_orderkey", "l_partkey").sample(0.1, 7)


@query("select doc_id, md5(text) as hash, length(text) as n, lower(substr(text, 1, 10)) as head, len(string_split(text, ' ')) as words, regexp_extract(text, '[a-z]+', 0) as word, text like '%the%' as has_the, levenshtein(substr(md5(text), 1, 8), '0123abcd') as distance from documents")
def string_suite(spark, d):
    t = F.col("text")
    return _t(spark, d, "documents").select("doc_id", F.md5("text").alias("hash"), F.length("text").cast("bigint").alias("n"), F.lower(F.substring("text", 1, 10)).alias("head"), F.size(F.split("text", " ")).cast("bigint").alias("words"), F.regexp_extract("text", "[a-z]+", 0).alias("word"), t.like("%the%").alias("has_the"), F.levenshtein(F.substring(F.md5("text"), 1, 8), F.lit("0123abcd")).cast("bigint").alias("distance"))


@query("select o_orderkey, cast(date_trunc('month', o_orderdate) as date) as month, datediff('day', date '1992-01-01', cast(o_orderdate as date)) as days, year(o_orderdate) as y, quarter(o_orderdate) as q, cast(o_orderdate + interval '1 month' as date) as later, epoch_us(o_orderdate) as us from orders")
def date_suite(spark, d):
    o, at = _t(spark, d, "orders"), F.col("o_orderdate")
    return o.select("o_orderkey", F.to_date(F.date_trunc("month", at)).alias("month"), F.datediff(F.to_date(at), F.lit("1992-01-01").cast("date")).cast("bigint").alias("days"), F.year(at).cast("bigint").alias("y"), F.quarter(at).cast("bigint").alias("q"), F.to_date(at + F.expr("interval 1 month")).alias("later"), F.unix_micros(at.cast("timestamp")).alias("us"))


@query("select p_partkey, cast(ceil(ln(p_size + 1) / ln(1.5)) as bigint) + 1 as bound, cast(floor(pow(p_size, 1.5)) as bigint) as power, ((p_partkey % 7) + 7) % 7 as m, p_partkey << 3 as shifted, round(abs(p_retailprice - 1000), 2) as off, greatest(p_size, 25) as big, least(p_size, 25) as small from part")
def math_suite(spark, d):
    s = F.col("p_size")
    return _t(spark, d, "part").select("p_partkey", (F.ceil(F.log(s + 1) / F.log(F.lit(1.5))).cast("bigint") + 1).alias("bound"), F.floor(F.pow(s, F.lit(1.5))).cast("bigint").alias("power"), F.pmod("p_partkey", F.lit(7)).cast("bigint").alias("m"), F.shiftleft("p_partkey", 3).alias("shifted"), F.round(F.abs(F.col("p_retailprice") - 1000), 2).alias("off"), F.greatest(s, F.lit(25)).alias("big"), F.least(s, F.lit(25)).alias("small"))


@query("select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 6) as squares, len(list_filter(embedding, lambda x: x > 0)) as positive, cast(list_min(embedding) as double) as low, cast(list_sort(embedding)[1] as double) as first_sorted, cast(embedding[2] as double) as second from embeddings")
def array_suite(spark, d):
    e = _t(spark, d, "embeddings")
    return e.select("vec_id", F.round(F.expr("aggregate(zip_with(embedding, embedding, (x, y) -> cast(x as double) * cast(y as double)), 0D, (s, v) -> s + v)"), 6).alias("squares"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"), F.array_min("embedding").cast("double").alias("low"), F.sort_array("embedding")[0].cast("double").alias("first_sorted"), F.element_at("embedding", 2).cast("double").alias("second"))


@query("select user_id, count(*) filter (where event_type = 'click') as clicks, count(distinct event_type) as kinds from events group by 1")
def map_suite(spark, d):
    n = _t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    kept = F.map_filter(F.transform_values("m", lambda k, v: v + 0), lambda k, v: v > 0)
    return m.select("user_id", F.coalesce(F.try_element_at(kept, F.lit("click")), F.lit(0)).cast("bigint").alias("clicks"), F.size(F.map_keys(kept)).cast("bigint").alias("kinds"))


@query("select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")
def json_suite(spark, d):
    e = _t(spark, d, "events")
    return e.select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("select cast(date_trunc('day', ts) as timestamp) as start, count(distinct user_id) as users, count(*) as n from events group by 1")
def tumbling_user_prop(spark, d):
    return _t(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 day")["start"].cast("timestamp_ntz").alias("start")).agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n"))


@query("select s as start, count(*) as n from (select unnest([time_bucket(interval '6 hours', ts), time_bucket(interval '6 hours', ts) - interval '6 hours', time_bucket(interval '6 hours', ts) - interval '12 hours', time_bucket(interval '6 hours', ts) - interval '18 hours']) as s from events) group by 1")
def sliding_event_counts(spark, d):
    return _t(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 day", "6 hours")["start"].cast("timestamp_ntz").alias("start")).agg(F.count("*").alias("n"))


@query("select user_id, count(*) as sessions, max(n) as longest from (select user_id, n as k, count(*) as n from (select *, sum(f) over (partition by user_id order by ts, event_id) as n from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval '6 hours' then 0 else 1 end as f from events)) group by 1, 2) group by 1")
def session_window_counts(spark, d):
    per = _t(spark, d, "events").groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "6 hours")).agg(F.count("*").alias("n"))
    return per.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))
