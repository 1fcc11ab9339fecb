"""Non-geometric graph of nations, ready-made chains, and a cloud of vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.operators import graphpart, metrics, related, sfc
from cellbalance.catalog import query, table

_FLOW = """flow as (select c.c_nationkey a, s.s_nationkey b, count(*) f from lineitem l join orders o on o.o_orderkey = l.l_orderkey join customer c on c.c_custkey = o.o_custkey join supplier s on s.s_suppkey = l.l_suppkey group by all)"""


def nation_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem").groupBy("l_orderkey", "l_suppkey").agg(F.count("*").alias("n"))
    orders, customer, supplier = (table(spark, sf_dir, t) for t in ("orders", "customer", "supplier"))
    star = li.join(orders.select("o_orderkey", "o_custkey"), li.l_orderkey == F.col("o_orderkey")).join(customer.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    star = star.join(supplier.select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return star.groupBy(F.col("c_nationkey").cast("long").alias("a"), F.col("s_nationkey").cast("long").alias("b")).agg(F.sum("n").alias("f"))


def nation_edges(flow: DataFrame) -> DataFrame:
    return flow.filter("a <> b").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum("f").alias("area"))


def nation_vertices(flow: DataFrame) -> DataFrame:
    return flow.groupBy(F.col("b").alias("v")).agg(F.sum("f").alias("weight"))


@query("nation_graph", f"with {_FLOW} select cast(least(a, b) as bigint) as nation_a, cast(greatest(a, b) as bigint) as nation_b, cast(sum(f) as bigint) as flow from flow where a <> b group by 1, 2")
def nation_graph(spark, sf_dir):
    return nation_edges(nation_flow(spark, sf_dir)).select(F.col("a").alias("nation_a"), F.col("b").alias("nation_b"), F.col("area").alias("flow"))


@query(
    "nation_bisection_brute",
    f"""with {_FLOW}, rf as (select x.n_regionkey a, y.n_regionkey b, sum(f) f from flow join nation x on x.n_nationkey = a join nation y on y.n_nationkey = b group by all),
masks as (select m.i m from range(1, 16) m(i)),
cuts as (select m, sum(case when ((m >> a) & 1) <> ((m >> b) & 1) then f else 0 end) cut, abs(2 * sum(case when ((m >> b) & 1) = 1 then f else 0 end) - sum(f)) off from rf, masks group by m)
select cast(m as bigint) as mask, cast(cut as bigint) as cut, cast(off as bigint) as imbalance from cuts""",
)
def nation_bisection(spark, sf_dir):
    """Every split of the five regions in two: cut flow and imbalance of each, for small exact checks."""
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_regionkey").cast("int").alias("r"))
    flow = nation_flow(spark, sf_dir)
    by = flow.join(nation.select(F.col("k").alias("a"), F.col("r").alias("ra")), "a").join(nation.select(F.col("k").alias("b"), F.col("r").alias("rb")), "b").groupBy("ra", "rb").agg(F.sum("f").alias("f"))
    every = by.withColumn("mask", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(15).cast("long")))).withColumns({f"s{n}": F.expr(f"shiftright(mask, r{n}) & 1") for n in "ab"})
    return every.groupBy("mask").agg(F.sum(F.when(F.col("sa") != F.col("sb"), F.col("f")).otherwise(0)).alias("cut"), F.abs(2 * F.sum(F.when(F.col("sb") == 1, F.col("f")).otherwise(0)) - F.sum("f")).alias("imbalance"))


@query("nation_kway")
def nation_kway(spark, sf_dir):
    flow = nation_flow(spark, sf_dir)
    return graphpart.multilevel(nation_vertices(flow), nation_edges(flow), 5)


def _chain(rows: str, p: int) -> str:
    return f"with c as ({rows}), s as (select *, coalesce(sum(w) over (order by pos rows between unbounded preceding and 1 preceding), 0) b, sum(w) over () t from c) select pos, cast(w as bigint) as weight, cast(least({p - 1}, ((2 * b + w) * {p}) // (2 * t)) as bigint) as rank_id from s"


def chain(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """pos, weight of a ready-made order."""
    if name == "documents":
        return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("pos"), F.col("n_chars").cast("long").alias("weight"))
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("pos"), F.length("html").cast("long").alias("weight"))


for _name, _rows in (("documents", "select doc_id pos, n_chars w from documents"), ("pages", "select page_id pos, length(html) w from pages")):

    @query(f"chain_{_name}", _chain(_rows, 20))
    def chain_midpoint(spark, sf_dir, name=_name):
        return sfc.cut(chain(spark, sf_dir, name), "pos", 20).select("pos", "weight", "rank_id")

    @query(f"chain_{_name}_count", f"with c as ({_rows}) select pos, cast(w as bigint) as weight, cast((row_number() over (order by pos) - 1) * 20 // count(*) over () as bigint) as rank_id from c")
    def chain_count(spark, sf_dir, name=_name):
        return sfc.cut(chain(spark, sf_dir, name), "pos", 20, "count").select("pos", "weight", "rank_id")

    for _how in ("greedy", "optimal"):

        @query(f"chain_{_name}_{_how}")
        def chain_other(spark, sf_dir, name=_name, how=_how):
            return sfc.cut(chain(spark, sf_dir, name), "pos", 20, how).select("pos", "weight", "rank_id")


@query(
    "chain_max_loads",
    f"with m as ({_chain('select doc_id pos, n_chars w from documents', 20)}), c as (select n_chars w, (row_number() over (order by doc_id) - 1) * 20 // count(*) over () r from documents) "
    "select 'midpoint' as how, cast(max(l) as bigint) as max_load from (select sum(weight) l from m group by rank_id) union all select 'count', cast(max(l) as bigint) from (select sum(w) l from c group by r)",
)
def chain_loads(spark, sf_dir):
    rows = chain(spark, sf_dir, "documents")
    out = [metrics.max_load(sfc.cut(rows, "pos", 20, how), 20).select(F.lit(how).alias("how"), "max_load") for how in ("midpoint", "count")]
    return out[0].union(out[1])


def vector_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = table(spark, sf_dir, "embeddings")
    return v.select("vec_id", "label", *[F.floor(F.col("embedding")[i].cast("double") * 1000000).cast("long").alias(f"g{n}") for i, n in enumerate("xyz")])


_VEC = "v as (select label, cast(floor(cast(embedding[1] as double) * 1000000) as bigint) gx, cast(floor(cast(embedding[2] as double) * 1000000) as bigint) gy, cast(floor(cast(embedding[3] as double) * 1000000) as bigint) gz from embeddings)"


@query(
    "voronoi_embeddings",
    f"""with {_VEC}, seeds as (select label seed, cast(floor(cast(sum(gx) as double) / count(*)) as bigint) sx, cast(floor(cast(sum(gy) as double) / count(*)) as bigint) sy, cast(floor(cast(sum(gz) as double) / count(*)) as bigint) sz from v group by label),
near as (select label, seed, row_number() over (partition by label, gx, gy, gz order by (gx - sx) * (gx - sx) + (gy - sy) * (gy - sy) + (gz - sz) * (gz - sz), seed) n, gx, gy, gz from v, seeds)
select label, seed as nearest_label, count(*) as cnt from near where n = 1 group by all""",
)
def voronoi(spark, sf_dir):
    v = vector_points(spark, sf_dir)
    seeds = v.groupBy(F.col("label").alias("seed")).agg(*[F.floor(F.sum(f"g{n}").cast("double") / F.count("*")).cast("long").alias(f"s{n}") for n in "xyz"])
    found = related.voronoi(v.groupBy("gx", "gy", "gz").agg(F.count("*").alias("weight")), seeds)
    return v.dropDuplicates(["label", "gx", "gy", "gz"]).join(found, ["gx", "gy", "gz"]).groupBy("label", F.col("part_id").alias("nearest_label")).agg(F.count("*").alias("cnt"))


@query("voronoi_descent")
def voronoi_descent(spark, sf_dir):
    v = vector_points(spark, sf_dir).groupBy("gx", "gy", "gz").agg(F.count("*").alias("weight"))
    seeds = vector_points(spark, sf_dir).groupBy(F.col("label").alias("seed")).agg(*[F.floor(F.avg(f"g{n}")).cast("long").alias(f"s{n}") for n in "xyz"])
    return related.voronoi(v, seeds, 3).groupBy("part_id").agg(F.count("*").alias("cells"), F.sum("weight").alias("weight"))
