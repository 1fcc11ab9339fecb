"""Operators around the methods: joins, aggregates, windows, set operations and functions a user needs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellbalance.operators.octree import CELL
from cellbalance.operators.store import written
from cellbalance.plans import sqltext as q
from cellbalance.plans import wedge
from cellbalance.catalog import query, table


def _ts(df: DataFrame, c: str) -> DataFrame:
    return df.withColumn(c, F.col(c).cast("timestamp"))


@query(
    "asof_orders",
    """with s as (select k.i k, cast(epoch_us(timestamp '1995-01-01') // 1000000 + k.i * 8640000 as bigint) at_ from range(0, 25) k(i)),
o as (select o_orderkey, cast(epoch_us(cast(o_orderdate as timestamp)) // 1000000 as bigint) t from orders)
select o_orderkey, max(k) as snapshot from o join s on at_ <= t group by o_orderkey""",
)
def asof_orders(spark, sf_dir):
    """The latest snapshot at or before each order: snapshots and orders in one order, last value seen.
    Ranges of 2^20 seconds are carried across by their own last snapshot, so no task sees all rows."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.expr("unix_seconds(cast(o_orderdate as timestamp))").alias("t"))
    s = spark.range(25).select(F.col("id").alias("k"), (F.lit(788918400) + F.col("id") * 8640000).alias("t"))
    both = o.select("o_orderkey", "t", F.lit(None).cast("long").alias("k")).union(s.select(F.lit(None).cast("long"), "t", "k"))
    both = both.withColumn("range", F.shiftright("t", 20))
    ends = both.groupBy("range").agg(F.max("k").alias("own")).withColumn("before", F.max("own").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)))
    w = Window.partitionBy("range").orderBy("t", F.col("k").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("in_range", F.last("k", True).over(w)).join(F.broadcast(ends.select("range", "before")), "range")
    return found.filter("o_orderkey is not null").select("o_orderkey", F.coalesce("in_range", "before").alias("snapshot")).filter("snapshot is not null")


@query(
    "interval_snapshots",
    "select cast(epoch_us(ts) // 1000000 // 259200 as bigint) - 6575 as snapshot, event_type, count(*) as cnt from events group by all",
)
def interval_snapshots(spark, sf_dir):
    """Interval join of events with three-day snapshots, with the day as the equality key."""
    ev = table(spark, sf_dir, "events").select("event_type", F.expr("unix_seconds(cast(ts as timestamp))").alias("t")).withColumn("day", F.expr("t div 86400"))
    snaps = spark.range(-5, 40).select(F.col("id").alias("snapshot"), ((F.col("id") + 6575) * 259200).alias("lo")).withColumn("hi", F.col("lo") + 259200)
    days = snaps.withColumn("day", F.explode(F.expr("sequence(lo div 86400, (hi - 1) div 86400)")))
    return ev.join(days, "day").filter("t >= lo and t < hi").groupBy("snapshot", "event_type").agg(F.count("*").alias("cnt"))


@query("anti_unlabelled_docs", "select doc_id, n_chars from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id)")
def anti_unlabelled(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_anti")


@query("semi_labelled_docs", "select doc_id, n_chars from documents d where exists (select 1 from labels l where l.doc_id = d.doc_id and l.quality = 1)")
def semi_labelled(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels").filter("quality = 1").select("doc_id"), "doc_id", "left_semi")


_FLAGS = "l_returnflag, l_linestatus"
for _kind, _group in (("rollup", f"rollup ({_FLAGS})"), ("cube", f"cube ({_FLAGS})"), ("grouping_sets", "grouping sets ((l_returnflag), (l_linestatus), ())")):

    @query(f"{_kind}_flags", f"select l_returnflag, l_linestatus, count(*) as cnt, cast(sum(cast(l_quantity as bigint)) as bigint) as qty from lineitem group by {_group}")
    def grouped_flags(spark, sf_dir, kind=_kind):
        li = table(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus", F.col("l_quantity").cast("long").alias("q"))
        keys = ["l_returnflag", "l_linestatus"]
        g = li.rollup(*keys) if kind == "rollup" else li.cube(*keys) if kind == "cube" else li.groupingSets([["l_returnflag"], ["l_linestatus"], []], *keys)
        return g.agg(F.count("*").alias("cnt"), F.sum("q").alias("qty"))


_TYPES = ("click", "view", "purchase", "signup", "logout")


@query("pivot_events", "select event_type, cast(sum(case when extract(hour from ts) < 6 then 1 else 0 end) as bigint) as q0, cast(sum(case when extract(hour from ts) between 6 and 11 then 1 else 0 end) as bigint) as q1, cast(sum(case when extract(hour from ts) between 12 and 17 then 1 else 0 end) as bigint) as q2, cast(sum(case when extract(hour from ts) >= 18 then 1 else 0 end) as bigint) as q3 from events group by event_type")
def pivot_events(spark, sf_dir):
    ev = table(spark, sf_dir, "events").select("event_type", F.concat(F.lit("q"), F.expr("hour(ts) div 6").cast("string")).alias("quarter"))
    return ev.groupBy("event_type").pivot("quarter", ["q0", "q1", "q2", "q3"]).agg(F.count(F.lit(1))).na.fill(0)


@query("window_ranks_docs", "select doc_id, row_number() over w as rn, rank() over w as rk, dense_rank() over w as drk, ntile(4) over w as nt from (select doc_id, source, n_chars from documents) window w as (partition by source order by n_chars desc, doc_id)")
def window_ranks(spark, sf_dir):
    w = Window.partitionBy("source").orderBy(F.col("n_chars").desc(), "doc_id")
    d = table(spark, sf_dir, "documents").select("doc_id", "source", "n_chars")
    return d.select("doc_id", *[f.over(w).cast("long").alias(n) for n, f in (("rn", F.row_number()), ("rk", F.rank()), ("drk", F.dense_rank()), ("nt", F.ntile(4)))])


@query("moving_sum_events", "select event_id, cast(sum(cast(round(value * 100) as bigint)) over (partition by user_id order by ts, event_id rows between 99 preceding and current row) as bigint) as sum100 from events")
def moving_sum(spark, sf_dir):
    """Trailing window of 100 rows, in hundredths, so that sums are exact in any engine."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-99, 0)
    return table(spark, sf_dir, "events").select("event_id", F.sum(F.round(F.col("value") * 100).cast("long")).over(w).alias("sum100"))


@query(
    "session_events",
    """with g as (select user_id, ts, case when lag(ts) over w is null or epoch_us(ts) - epoch_us(lag(ts) over w) >= 7200000000 then 1 else 0 end s from events window w as (partition by user_id order by ts)),
n as (select user_id, ts, sum(s) over (partition by user_id order by ts rows unbounded preceding) k from g) select user_id, count(*) as cnt, cast(min(epoch_us(ts)) // 1000000 as bigint) as started from n group by user_id, k""",
)
def session_events(spark, sf_dir):
    ev = _ts(table(spark, sf_dir, "events").select("user_id", "ts"), "ts")
    return ev.groupBy("user_id", F.session_window("ts", "2 hours").alias("s")).agg(F.count("*").alias("cnt")).select("user_id", "cnt", F.expr("unix_seconds(s.start)").alias("started"))


@query("tumbling_events", "select cast(epoch_us(ts) // 86400000000 * 86400 as bigint) as started, count(*) as cnt from events group by 1")
def tumbling(spark, sf_dir):
    ev = _ts(table(spark, sf_dir, "events").select("ts"), "ts")
    return ev.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("cnt")).select(F.expr("unix_seconds(w.start)").alias("started"), "cnt")


@query("sliding_events", "select cast((epoch_us(ts) // 86400000000 - k.i) * 86400 as bigint) as started, count(*) as cnt from events, range(0, 3) k(i) group by 1")
def sliding(spark, sf_dir):
    ev = _ts(table(spark, sf_dir, "events").select("ts"), "ts")
    return ev.groupBy(F.window("ts", "3 days", "1 day").alias("w")).agg(F.count("*").alias("cnt")).select(F.expr("unix_seconds(w.start)").alias("started"), "cnt")


@query("setops_leaves", f"select 'stable' as kind, count(*) as cnt from (with {q.wedge(512)} select lv, cx, cy, cz from raw intersect select 1, cx, cy, cz from n1) union all select 'changed', count(*) from (with {q.wedge(512)} select lv, cx, cy, cz from raw except select 1, cx, cy, cz from n1)")
def setops(spark, sf_dir):
    b = wedge.build(spark, wedge.wedge(spark, sf_dir, 512), kept=True)
    raw, start = b.raw.select(*CELL), b.start.select(*CELL)
    return raw.intersect(start).agg(F.lit("stable").alias("kind"), F.count("*").alias("cnt")).union(raw.exceptAll(start).agg(F.lit("changed"), F.count("*")))


@query("json_props", "select cast(json_extract(props, '$.k') as bigint) as k, count(*) as cnt from events group by 1")
def json_props(spark, sf_dir):
    parsed = table(spark, sf_dir, "events").select(F.from_json("props", "k bigint").alias("p"))
    return parsed.groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("cnt"))


@query("array_stats_embeddings", "select vec_id, cast(len(embedding) as integer) as dims, round(list_max(cast(embedding as double[])), 6) as top, round(list_min(cast(embedding as double[])), 6) as low from embeddings")
def array_stats(spark, sf_dir):
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    return v.select("vec_id", F.size("e").alias("dims"), F.round(F.array_max("e"), 6).alias("top"), F.round(F.array_min("e"), 6).alias("low"))


@query("url_hosts", "select lower(regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1)) as host, count(*) as pages, cast(sum(length(html)) as bigint) as chars from pages group by 1")
def url_hosts(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select(F.lower(F.regexp_extract("url", "^[a-z]+://([^/?#:]+)", 1)).alias("host"), F.length("html").cast("long").alias("n"))
    return p.groupBy("host").agg(F.count("*").alias("pages"), F.sum("n").alias("chars"))


@query("turn_gaps", "select conv_id, turn, cast(length(text) - lag(length(text)) over (partition by conv_id order by turn) as integer) as growth from conversations")
def turn_gaps(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", (F.length("text") - F.lag(F.length("text")).over(w)).alias("growth"))


@query("topk_leaves_per_rank", f"with {wedge._ranked('hilbert')} select rank_id, level, cx, cy, cz, weight from (select {q.CELL}, cast(w as bigint) as weight, r as rank_id, row_number() over (partition by r order by w desc, lv, cx, cy, cz) n from asg) where n <= 2")
def topk_leaves(spark, sf_dir):
    asg = wedge.hilbert_assignment(spark, sf_dir)
    w = Window.partitionBy("rank_id").orderBy(F.col("weight").desc(), *CELL)
    return asg.withColumn("n", F.row_number().over(w)).filter("n <= 2").select("rank_id", *CELL, "weight")


@query("percentiles_docs", "select source, round(quantile_cont(cast(n_chars as double), 0.5), 6) as p50, round(quantile_cont(cast(n_chars as double), 0.9), 6) as p90 from documents group by source")
def percentiles(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("source", F.col("n_chars").cast("double").alias("n"))
    return d.groupBy("source").agg(F.round(F.percentile("n", 0.5), 6).alias("p50"), F.round(F.percentile("n", 0.9), 6).alias("p90"))


@query("occupied_cells", f"with {q.CLOUD} select count(distinct (gx >> 7) * 64 + (gy >> 7) * 8 + (gz >> 7)) as occupied from cloud")
def occupied(spark, sf_dir):
    return wedge.cloud(spark, sf_dir).agg(F.count_distinct(*[F.shiftright(g, 7) for g in ("gx", "gy", "gz")]).alias("occupied"))


@query("regression_lineitem", "select round(corr(l_quantity, l_extendedprice), 6) as corr, round(regr_slope(l_extendedprice, l_quantity), 4) as slope, round(regr_r2(l_extendedprice, l_quantity), 6) as r2 from lineitem")
def regression(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem")
    return li.agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.regr_r2("l_extendedprice", "l_quantity"), 6).alias("r2"))


def _roots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Columns of roots that hold rows of lineitem."""
    return wedge.cloud(spark, sf_dir).select(F.shiftright("gx", 8).alias("cx"), F.shiftright("gy", 8).alias("cy")).distinct()


_PATHS = "with recursive t(level, path) as (select 0, {root} from {roots} union all select level + 1, path || c.d from t, (values ('0'), ('3'), ('7')) c(d) where level < 3) select cast(level as integer) as level, path from t"


@query("recursive_paths", _PATHS.format(root="cast(cx as varchar) || '.' || cast(cy as varchar)", roots="roots_").replace("with recursive", f"with recursive {q.CLOUD}, roots_ as (select distinct gx >> 8 cx, gy >> 8 cy from cloud),"))
def recursive_paths(spark, sf_dir):
    """Paths of three octants below each root that holds rows."""
    return spark.sql(_PATHS.replace("{root}", "cast(cx as string) || '.' || cast(cy as string)"), roots=written(_roots(spark, sf_dir)))


@query("lateral_children", f"with {q.CLOUD} select distinct gx >> 8 as cx, gy >> 8 as cy, 8 as children from cloud")
def lateral_children(spark, sf_dir):
    """The octants of each root that holds rows, as a lateral join."""
    kids = spark.range(8).select(F.col("id").alias("octant"))
    return _roots(spark, sf_dir).alias("r").lateralJoin(kids).groupBy("cx", "cy").agg(F.count("*").cast("int").alias("children"))


@query("full_outer_ranks", "select cast(i.i as bigint) as rank_id, c.n as customers from range(0, 30) i(i) full join (select c_nationkey k, count(*) n from customer group by 1) c on c.k = i.i")
def full_outer(spark, sf_dir):
    c = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").cast("long").alias("k")).agg(F.count("*").alias("customers"))
    return spark.range(30).join(c, F.col("id") == F.col("k"), "full").select(F.col("id").alias("rank_id"), "customers")


@query("star_join_regions", "select r_name, count(*) as lines from lineitem l join orders o on o.o_orderkey = l.l_orderkey join customer c on c.c_custkey = o.o_custkey join nation n on n.n_nationkey = c.c_nationkey join region r on r.r_regionkey = n.n_regionkey group by r_name")
def star_join(spark, sf_dir):
    t = {n: table(spark, sf_dir, n) for n in ("lineitem", "orders", "customer", "nation", "region")}
    li = t["lineitem"].groupBy("l_orderkey").agg(F.count("*").alias("n"))
    j = li.join(t["orders"].select("o_orderkey", "o_custkey"), li.l_orderkey == F.col("o_orderkey")).join(t["customer"].select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    j = j.join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(t["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.sum("n").alias("lines"))


@query("sampled_lineitem", "select l_partkey, count(*) as cnt from lineitem where l_partkey % 16 = 3 group by 1")
def sampled(spark, sf_dir):
    """Deterministic sampling of keys, the way cut planes are sampled."""
    return table(spark, sf_dir, "lineitem").filter("l_partkey % 16 = 3").groupBy("l_partkey").agg(F.count("*").alias("cnt"))
