"""Variants of tree and order, physical migration, comparisons, and the surrounding operators of Spark."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from cellbalance.catalog import query, table
from cellbalance.functions import sqlfuncs
from cellbalance.functions.curves import hilbert_index
from cellbalance.operators import adjacency, baselines, contacts, diffusion, graphpart, metrics, octree, related, sfc
from cellbalance.operators.domain import Domain, cell_of
from cellbalance.operators.octree import CELL
from cellbalance.operators.store import fresh_path, written
from cellbalance.plans import extras, graph, hopper, wedge
from cellbalance.plans import sqltext as q
from cellbalance.plans.wedge import BITS, DEEP, DOM, EIGHTH, HALF, LEAF, P
from cellbalance.sources import lattice, layout
from cellbalance.streaming import rebalance as streams

# --- tree and order variants


@query(
    "adapt_two_levels",
    f"""with {q.wedge(EIGHTH)},
inner_ as (select pyr.* from pyr, tot where w * {P} > t and lv < 2),
deep as (select i.* from inner_ i where lv = 0 or exists (select 1 from inner_ u where u.lv = i.lv - 1 and u.cx = i.cx >> 1 and u.cy = i.cy >> 1 and u.cz = i.cz >> 1)),
nodes as (select 0 lv, cx, cy, cz from roots union all select lv + 1, 2 * cx + ox, 2 * cy + oy, 2 * cz + oz from deep, octants),
tree as (select n.*, coalesce(p.w, 0) w from nodes n left join pyr p on p.lv = n.lv and p.cx = n.cx and p.cy = n.cy and p.cz = n.cz
  where not exists (select 1 from deep i where i.lv = n.lv and i.cx = n.cx and i.cy = n.cy and i.cz = n.cz))
{LEAF} from tree""",
)
def adapt_two_levels(spark, sf_dir):
    """Two levels in one call, from the roots."""
    pyr = written(octree.pyramid(wedge.wedge(spark, sf_dir, EIGHTH), DOM))
    return octree.adapt(octree.weighed(octree.uniform(spark, DOM, 0), pyr), pyr, DOM, P, max_delta=2)


@query("sparse_leaves", f"with {q.wedge(EIGHTH)} {LEAF} from leaves where w > 0")
def sparse_leaves(spark, sf_dir):
    """The sparse forest: closed leaves without the empty ones."""
    b = wedge.build(spark, wedge.wedge(spark, sf_dir, EIGHTH))
    return octree.closed_leaves(spark, b.raw, b.pyr, DOM, keep_empty=False)


_INNER_KEY = " + ".join(f"(((x >> {b}) & 1) << {3 * b + 2}) + (((y >> {b}) & 1) << {3 * b + 1}) + (((z >> {b}) & 1) << {3 * b})" for b in range(DEEP))


@query(
    "root_order_assign",
    f"""with {q.wedge(HALF)}, corner as (select *, cx << ({DEEP} - lv) fx, cy << ({DEEP} - lv) fy, cz << ({DEEP} - lv) fz from leaves),
inner_ as (select *, fx & {(1 << DEEP) - 1} x, fy & {(1 << DEEP) - 1} y, fz & {(1 << DEEP) - 1} z, (fx >> {DEEP}) * 4 + (fy >> {DEEP}) + (fz >> {DEEP}) root from corner),
keyed as (select lv, cx, cy, cz, w, (root << {3 * DEEP}) + ((({_INNER_KEY}) >> (3 * ({DEEP} - lv))) << (3 * ({DEEP} - lv))) k from inner_),
{q.midpoint('keyed', P)} select {q.CELL}, cast(w as bigint) as weight, r as rank_id from asg""",
)
def root_order_assign(spark, sf_dir):
    """Roots in lexicographic order, the Morton curve inside each."""
    return sfc.balance(wedge.half(spark, sf_dir).leaves, DOM, P, "morton", root_order="lexicographic")


@query("uniform_refinement_loads", f"with {q.wedge(HALF)}, cells as (select a.i cx, b.i cy, c.i cz, 2 lv, coalesce(p.w, 0) w from range(0, 16) a(i) cross join range(0, 16) b(i) cross join range(0, 4) c(i) left join pyr p on p.lv = 2 and p.cx = a.i and p.cy = b.i and p.cz = c.i), {q.morton('cells', DEEP, BITS)}, {q.midpoint('keyed', P)} select cast(r as bigint) as rank_id, cast(sum(w) as bigint) as load from asg group by r")
def uniform_refinement(spark, sf_dir):
    """Loads if every subdomain is refined alike and then cut: a quarter of the leaves too many."""
    pyr = octree.pyramid(wedge.wedge(spark, sf_dir, HALF), DOM)
    leaves = octree.weighed(octree.uniform(spark, DOM, 2), pyr)
    return sfc.balance(leaves, DOM, P, "morton").groupBy("rank_id").agg(F.sum("weight").alias("load"))


_STATIC_HILBERT = f"""{wedge._ranked('hilbert')}, start as (select cx, cy, cz, row_number() over (order by cx, cy, cz) - 1 r from n1),
up as (select cx, cy, r from (select cx >> 1 cx, cy >> 1 cy, s.r, row_number() over (partition by cx >> 1, cy >> 1 order by w desc, s.r) n from start s join n1 using (cx, cy, cz)) where n = 1),
inherited as (select a.*, coalesce(s.r, u.r) was from asg a left join start s on a.lv >= 1 and s.cx = a.cx >> (a.lv - 1) and s.cy = a.cy >> (a.lv - 1) and s.cz = a.cz >> (a.lv - 1) left join up u on a.lv = 0 and u.cx = a.cx and u.cy = a.cy)"""


@query("physical_migration", f"with {_STATIC_HILBERT} select cast(r as bigint) as new_rank, cast(sum(w) as bigint) as rows_moved from inherited where r <> was and w > 0 group by r")
def physical_migration(spark, sf_dir):
    """Rows that an incremental rewrite of the layout touches, by the rank that receives them."""
    b = wedge.half(spark, sf_dir)
    plan = written(metrics.migration(wedge.inherited(b), sfc.balance(b.leaves, DOM, P)))
    moved = layout.moved_rows(b.points, plan.filter("weight > 0").select(*CELL), DOM)
    return moved.join(plan.select(*CELL, F.col("new_rank").cast("long").alias("new_rank")), CELL).groupBy("new_rank").agg(F.count("*").alias("rows_moved"))


@query("layout_box_rows", f"with {q.wedge(HALF)} select gx, gy, gz, count(*) as cnt from pts where gx < 256 and gy between 256 and 767 group by all")
def layout_box(spark, sf_dir):
    """Rows of a box, read from the layout by key ranges."""
    b, path = wedge.half(spark, sf_dir), fresh_path(spark, "layout")
    layout.write(b.points, written(sfc.balance(b.leaves, DOM, P)), DOM, P, path)
    found = layout.read_box(spark, path, DOM, (0, 4, 0), (3, 11, 3), 2)
    return found.filter("gx < 256 and gy between 256 and 767").groupBy("gx", "gy", "gz").agg(F.count("*").alias("cnt"))


@query("bucketed_rank_rows", f"with {wedge._ranked('hilbert')} select cast(r as bigint) as rank_id, cast(sum(w) as bigint) as cnt from asg where w > 0 group by r")
def bucketed_rows(spark, sf_dir):
    """Rows by rank from a table that is bucketed by rank: the aggregate needs no shuffle."""
    b, name = wedge.half(spark, sf_dir), f"rows_{uuid.uuid4().hex}"
    layout.bucketed(b.points, written(sfc.balance(b.leaves, DOM, P)), DOM, name)
    try:
        return written(spark.table(name).groupBy("rank_id").agg(F.count("*").alias("cnt")))
    finally:
        spark.sql(f"drop table {name}")


# --- comparisons

PARTS = 32


@query("decomposition_comparison")
def decomposition_comparison(spark, sf_dir):
    """32 parts of the half-filled box by bisection, kd-tree, sections, Voronoi cells and deformed planes,
    against both curves on adapted leaves and the uniform start of 4 x 4 x 2 bricks."""
    b = wedge.half(spark, sf_dir)
    cells = written(related.columns_of(b.points))
    coarse = written(octree.pyramid(b.points, DOM).filter("level = 2").select(*[F.col(f"c{n}").alias(f"g{n}") for n in "xyz"], "weight"))
    planes = related.deform(cells, [1024 * k // PARTS for k in range(1, PARTS)], "gx")
    seeds = spark.range(PARTS).select(F.col("id").alias("seed"), F.expr("id div 8 * 256 + 128").alias("sx"), F.expr("id div 2 % 4 * 256 + 128").alias("sy"), F.expr("id % 2 * 512 + 256").alias("sz"))
    bricks = F.expr("shiftright(gx, 8) * 8 + shiftright(gy, 8) * 2 + shiftright(gz, 9)")
    found = {
        "bricks": cells.withColumn("part_id", bricks),
        "bisection": related.rcb(cells, 5),
        "orthogonal_bisection": related.rcb(cells, 5, "longest"),
        "kd_tree": related.kdtree(coarse, 5),
        "sections": related.multisection(cells, (4, 4, 2)),
        "voronoi": related.voronoi(cells, seeds),
        "voronoi_centred": related.voronoi(cells, seeds, 2),
        "deformed_planes": cells.withColumn("part_id", sum(((F.col("gx") >= x).cast("long") for x in planes), F.lit(0).cast("long"))),
        "morton": sfc.balance(b.leaves, DOM, PARTS, "morton").withColumnRenamed("rank_id", "part_id"),
        "hilbert": sfc.balance(b.leaves, DOM, PARTS).withColumnRenamed("rank_id", "part_id"),
    }
    out = None
    for name, parts in found.items():
        loads = parts.groupBy("part_id").agg(F.sum("weight").alias("load"))
        row = loads.agg(F.lit(name).alias("method"), F.count("*").alias("parts_used"), F.max("load").alias("max_load"), F.round(F.max("load") * PARTS / F.sum("load"), 6).alias("ratio"))
        out = row if out is None else out.union(row)
    return out


@query("largest_first_loads")
def largest_first_loads(spark, sf_dir):
    """Largest loads of placements that ignore neighbours, against the Hilbert cut."""
    leaves, out = wedge.half(spark, sf_dir).leaves, None
    for name, asg in (("largest_first", baselines.largest_first(leaves, P)), ("hashed", baselines.hashed(leaves, P)), ("hilbert", sfc.balance(leaves, DOM, P))):
        row = metrics.max_load(asg, P).select(F.lit(name).alias("method"), "max_load", "ratio")
        out = row if out is None else out.union(row)
    return out


def _chain_loads(p: int) -> str:
    return (
        f"select {p} as p, 'midpoint' as how, cast(max(l) as bigint) as max_load from (select sum(weight) l from ({graph._chain('select doc_id pos, n_chars w from documents', p)}) group by rank_id) union all "
        f"select {p}, 'count', cast(max(l) as bigint) from (select sum(w) l from (select n_chars w, (row_number() over (order by doc_id) - 1) * {p} // count(*) over () r from documents) group by r)"
    )


@query("chain_loads_by_p", " union all ".join(map(_chain_loads, (8, 20, 64))))
def chain_loads_by_p(spark, sf_dir):
    """The chain of documents in 8, 20 and 64 runs, weights against counts."""
    rows, out = graph.chain(spark, sf_dir, "documents"), None
    for p in (8, 20, 64):
        for how in ("midpoint", "count"):
            row = metrics.max_load(sfc.cut(rows, "pos", p, how), p).select(F.lit(p).alias("p"), F.lit(how).alias("how"), "max_load")
            out = row if out is None else out.union(row)
    return out


@query("chain_cuts_compared")
def chain_cuts_compared(spark, sf_dir):
    """All four cuts of the chain of documents: none is below the optimal one."""
    rows, out = written(graph.chain(spark, sf_dir, "documents")), None
    for p in (8, 20, 64):
        for how in ("midpoint", "count", "greedy", "optimal"):
            row = metrics.max_load(sfc.cut(rows, "pos", p, how), p).select(F.lit(p).alias("p"), F.lit(how).alias("how"), "max_load", "ratio")
            out = row if out is None else out.union(row)
    return out


@query("nation_parts")
def nation_parts(spark, sf_dir):
    """The graph of nations in 2 and 5 parts by multilevel k-way and by repartitioning from nations dealt in
    turn: largest load, cut flow and weight moved."""
    flow = written(graph.nation_flow(spark, sf_dir))
    v, e, rows = written(graph.nation_vertices(flow)), written(graph.nation_edges(flow)), []
    for p in (2, 5):
        old = written(v.select("v", (F.col("v") % p).alias("part")))
        for name, parts in (("dealt", old), ("multilevel_kway", graphpart.multilevel(v, e, p)), ("unified_repartition", graphpart.repartition(v, e, old, p))):
            parts = written(parts)
            most = v.join(parts, "v").groupBy("part").agg(F.sum("weight").alias("w")).agg(F.max("w")).first()[0]
            rows.append((name, p, most, graphpart.cut_area(parts, e), graphpart.moved_weight(parts, old, v)))
    return spark.createDataFrame(rows, "method string, parts int, max_load long, cut long, moved_weight long")


VECTORS = Domain((4, 4, 4), 2)
_VECTOR_CELLS = f"""{graph._VEC}, box as (select min(gx) xl, max(gx) xh, min(gy) yl, max(gy) yh, min(gz) zl, max(gz) zh from v),
pts as (select (gx - xl) * 1024 // (xh - xl + 1) gx, (gy - yl) * 1024 // (yh - yl + 1) gy, (gz - zl) * 1024 // (zh - zl + 1) gz from v, box),
cells as (select 2 lv, gx >> 6 cx, gy >> 6 cy, gz >> 6 cz, count(*) w from pts group by all),
{q.morton('cells', 2, VECTORS.key_bits, 'mk')}, {q.midpoint('mk', 16, 'ma')}, {q.hilbert('cells', 2, VECTORS.key_bits, 'hk')}, {q.midpoint('hk', 16, 'ha')}"""


@query("vector_curves", f"with {_VECTOR_CELLS} select 'morton' as algo, cast(r as bigint) as rank_id, cast(sum(w) as bigint) as load from ma group by r union all select 'hilbert', cast(r as bigint), cast(sum(w) as bigint) from ha group by r")
def vector_curves(spark, sf_dir):
    """The cloud of vectors cut into 16 runs along both curves."""
    from cellbalance.operators import domain

    points = domain.quantize(graph.vector_points(spark, sf_dir).select("gx", "gy", "gz").withColumnsRenamed({"gx": "x", "gy": "y", "gz": "z"}), ("x", "y", "z")).select("gx", "gy", "gz")
    cells = written(octree.pyramid(points, VECTORS).filter("level = 2"))
    out = None
    for curve in ("morton", "hilbert"):
        row = sfc.balance(cells, VECTORS, 16, curve).groupBy("rank_id").agg(F.sum("weight").alias("load")).select(F.lit(curve).alias("algo"), "rank_id", "load")
        out = row if out is None else out.union(row)
    return out


# --- surrounding operators


@query("hinted_joins", "select how, count(*) as pairs, cast(sum(l_quantity) as double) as quantity from lineitem join orders on l_orderkey = o_orderkey, (select unnest(['shuffle_hash', 'merge']) how) group by how")
def hinted_joins(spark, sf_dir):
    """Shuffled hash join and sort-merge join by hint."""
    li, orders, out = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity"), table(spark, sf_dir, "orders").select("o_orderkey"), None
    for how in ("shuffle_hash", "merge"):
        row = li.join(orders.hint(how), F.col("l_orderkey") == F.col("o_orderkey")).agg(F.lit(how).alias("how"), F.count("*").alias("pairs"), F.sum("l_quantity").alias("quantity"))
        out = row if out is None else out.union(row)
    return out


@query("theta_join_parts", "with p as (select p_partkey pid, cast(20 * p_size as bigint) gx, cast(floor(p_retailprice / 2) as bigint) gy, p_partkey % 1000 gz from part where p_partkey < 400) select a.pid as pid_a, b.pid as pid_b from p a join p b on a.pid < b.pid and (a.gx - b.gx) * (a.gx - b.gx) + (a.gy - b.gy) * (a.gy - b.gy) + (a.gz - b.gz) * (a.gz - b.gz) <= 2500")
def theta_join(spark, sf_dir):
    """The nested-loop reference of contact detection on the parts of least number."""
    return contacts.brute_force(hopper.part_points(spark, sf_dir).filter("pid < 400"), 50)


@query("hilbert_udf_check", "select cast(0 as bigint) as differing")
def hilbert_udf_check(spark, sf_dir):
    """Keys of the column expression against a pandas UDF of the published form: no leaf differs."""
    bits = BITS

    @F.pandas_udf("long")
    def reference(x: pd.Series, y: pd.Series, z: pd.Series) -> pd.Series:
        return pd.Series([hilbert_index((a, b, c), bits) for a, b, c in zip(x, y, z, strict=True)])

    # a table: Spark would push the comparison below the distinct, to every row
    cells = written(wedge.cloud(spark, sf_dir).select(F.lit(DEEP).alias("level"), *cell_of(DOM, DEEP)).distinct())
    keyed = sfc.keyed(cells, DOM, "hilbert").withColumn("want", reference("cx", "cy", "cz"))
    return keyed.filter("curve_key <> want").agg(F.count("*").alias("differing"))


@query("observed_rows", "select count(*) as rows, cast(max(l_partkey) as bigint) as largest_part from lineitem")
def observed_rows(spark, sf_dir):
    """Metrics observed beside a job, without a second pass."""
    seen = Observation(f"rows-{uuid.uuid4().hex}")
    table(spark, sf_dir, "lineitem").select("l_partkey").observe(seen, F.count(F.lit(1)).alias("rows"), F.max("l_partkey").alias("largest_part")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["rows"], seen.get["largest_part"])], "rows long, largest_part long")


@query("approximate_cells", "select true as close")
def approximate_cells(spark, sf_dir):
    """Occupied lattice cells, approximately against exactly: within a tenth."""
    cell = F.struct(*[F.shiftright(f"g{n}", 4).alias(n) for n in "xyz"])
    row = wedge.cloud(spark, sf_dir).agg(F.approx_count_distinct(F.xxhash64(cell), 0.02).alias("a"), F.count_distinct(cell).alias("e"))
    return row.select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e")).alias("close"))


@query("rank_shares", "select doc_id, round(percent_rank() over (order by n_chars, doc_id), 6) as share, round(cume_dist() over (order by n_chars, doc_id), 6) as upto, cast(ntile(10) over (order by n_chars, doc_id) as integer) as tenth from documents")
def rank_shares(spark, sf_dir):
    w = Window.orderBy("n_chars", "doc_id")
    return table(spark, sf_dir, "documents").select("doc_id", F.round(F.percent_rank().over(w), 6).alias("share"), F.round(F.cume_dist().over(w), 6).alias("upto"), F.ntile(10).over(w).alias("tenth"))


@query("page_of_orders", "select o_orderkey, round(o_totalprice, 2) as price from orders order by o_totalprice desc, o_orderkey limit 25 offset 50")
def page_of_orders(spark, sf_dir):
    """The third page of the dearest orders."""
    o = table(spark, sf_dir, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(50).limit(25)
    return o.select("o_orderkey", F.round("o_totalprice", 2).alias("price"))


_SETS = "a as (select l_suppkey % 7 k, l_linenumber n from lineitem where l_returnflag = 'R'), b as (select l_suppkey % 7 k, l_linenumber n from lineitem where l_returnflag = 'A')"


@query("multiset_operations", f"with {_SETS} select 'except' as op, k, count(*) as cnt from (select * from a except all select * from b) group by k union all select 'intersect', k, count(*) from (select * from a intersect all select * from b) group by k")
def multiset_operations(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select((F.col("l_suppkey") % 7).alias("k"), F.col("l_linenumber").alias("n"), "l_returnflag")
    a, b = (li.filter(F.col("l_returnflag") == f).drop("l_returnflag") for f in "RA")
    parts = [x.groupBy("k").agg(F.count("*").alias("cnt")).select(F.lit(op).alias("op"), "k", "cnt") for op, x in (("except", a.exceptAll(b)), ("intersect", a.intersectAll(b)))]
    return parts[0].union(parts[1])


@query("pandas_median", "select l_returnflag, round(median(l_quantity), 6) as median from lineitem group by l_returnflag")
def pandas_median(spark, sf_dir):
    """A grouped pandas aggregate."""

    @F.pandas_udf("double")
    def middle(v: pd.Series) -> float:
        return float(v.median())

    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(middle("l_quantity"), 6).alias("median"))


@query("table_functions", "select cast(1 as integer) as level, 2 * a.i + x.i as cx, 2 * b.i + y.i as cy, z.i as cz from range(0, 4) a(i), range(0, 4) b(i), range(0, 2) x(i), range(0, 2) y(i), range(0, 2) z(i)")
def table_functions(spark, sf_dir):
    """Children of the roots through the table function, by a lateral join in SQL."""
    sqlfuncs.register(spark)
    octree.uniform(spark, DOM, 0).createOrReplaceTempView("root_cells")
    return spark.sql("select c.level, c.cx, c.cy, c.cz from root_cells r, lateral octree_children(r.level, r.cx, r.cy, r.cz) c")


@query("sql_keys", "with c as (select a.i x, b.i y, c.i z from range(0, 8) a(i), range(0, 8) b(i), range(0, 8) c(i)) select x, y, z, " + " + ".join(f"(((x >> {b}) & 1) << {3 * b + 2}) + (((y >> {b}) & 1) << {3 * b + 1}) + (((z >> {b}) & 1) << {3 * b})" for b in range(3)) + " as k, x >> 1 as cell from c")
def sql_keys(spark, sf_dir):
    """Keys and cells through the registered SQL functions."""
    sqlfuncs.register(spark)
    return spark.sql("select x, y, z, morton_key(x, y, z) as k, cell_of(x, 1) as cell from (select id div 64 as x, id div 8 % 8 as y, id % 8 as z from range(512))")


_ORDERS = "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string"


@query("scan_with_schema", "select o_orderstatus, count(*) as cnt, round(sum(o_totalprice), 2) as price from orders where o_totalprice > 1000 group by o_orderstatus")
def scan_with_schema(spark, sf_dir):
    """A scan with a declared schema: two columns read, the filter pushed down."""
    o = spark.read.schema(_ORDERS).parquet(f"{sf_dir}/orders.parquet").filter("o_totalprice > 1000")
    return o.groupBy("o_orderstatus").agg(F.count("*").alias("cnt"), F.round(F.sum("o_totalprice"), 2).alias("price"))


@query("lattice_source", "select p_partkey as pid, cast(p_partkey // 30 as double) * 0.5 as x, cast(p_partkey // 6 % 5 as double) * 0.5 as y, cast(p_partkey % 6 as double) * 0.5 as z, cast(0.25 as double) as radius from part")
def lattice_source(spark, sf_dir):
    """A particle for each part, on sites from the partitioned Python data source, as many as part keys need."""
    spark.dataSource.register(lattice.LatticeSource)
    ids = extras.part_ids(spark, sf_dir).withColumnRenamed("id", "pid")
    layers = (ids.agg(F.max("pid")).first()[0] or 0) // 30 + 1
    return spark.read.format("lattice").option("nx", layers).option("ny", 5).option("nz", 6).option("spacing", 0.5).load().join(ids.hint("merge"), "pid")


@query("cubic_velocities", "select cast(count(*) as integer) as spheres, true as bounded, true as differ from part")
def cubic_velocities(spark, sf_dir):
    """The lattice start, a sphere for each part: velocities within one unit along each axis, and not all the same."""
    v = lattice.cubic_of(extras.part_ids(spark, sf_dir), 6, 6)
    inside = F.bool_and(*[F.greatest(*[F.abs(f"v{n}") for n in "xyz"]) <= 1.0])
    return v.agg(F.count("*").cast("int").alias("spheres"), inside.alias("bounded"), (F.min(F.struct("vx", "vy", "vz")) < F.max(F.struct("vx", "vy", "vz"))).alias("differ"))


@query("kinematic_fall", "select p_partkey as pid, round(greatest(0.5, cast(p_partkey % 6 as double) - 0.5 * 1.5 * 1.5), 6) as z from part")
def kinematic_fall(spark, sf_dir):
    """Free fall of the resting lattice, a particle for each part, after 150 steps, in closed form."""
    return lattice.drop(lattice.cubic_of(extras.part_ids(spark, sf_dir), 6, 6).withColumn("vz", F.lit(0.0)), 150).select("pid", F.round("z", 6).alias("z"))


@query("streamed_to_memory", "select event_type, count(*) as cnt from events group by event_type")
def streamed_to_memory(spark, sf_dir):
    """A bounded stream into the memory sink."""
    name = f"held_{uuid.uuid4().hex}"
    stream = streams.event_stream(spark, f"{sf_dir}/events.parquet*").groupBy("event_type").agg(F.count("*").alias("cnt"))
    stream.writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return written(spark.table(name))


@query("streamed_rate", "select true as gapless")
def streamed_rate(spark, sf_dir):
    """Rows of the rate source come numbered without gaps."""
    name = f"rate_{uuid.uuid4().hex}"
    run = spark.readStream.format("rate").option("rowsPerSecond", 50).load().writeStream.format("memory").queryName(name).trigger(processingTime="500 milliseconds").start()
    try:
        for _ in range(60):
            run.awaitTermination(1)
            if spark.table(name).count() >= 50:
                break
    finally:
        run.stop()
    return written(spark.table(name).agg((F.max("value") + 1 == F.count_distinct("value")).alias("gapless")))


@query("partition_of_neighbours", f"with {q.wedge(HALF)}, {q.touching('leaves', DEEP)} select count(*) as pairs, cast(max(abs(la - lb)) as integer) as largest_step from touch")
def partition_of_neighbours(spark, sf_dir):
    """Touching leaves, and the largest difference of levels among them."""
    pairs = adjacency.full(wedge.half(spark, sf_dir).leaves, DOM)
    return pairs.agg(F.count("*").alias("pairs"), F.max(F.abs(F.col("src_level") - F.col("dst_level"))).cast("int").alias("largest_step"))


def moved_between(old: DataFrame, new: DataFrame) -> DataFrame:
    return metrics.migration_volume(old, new)


@query("diffusion_run_regularly")
def diffusion_run_regularly(spark, sf_dir):
    """Diffusion called again and again, one round a call, from the assignment the call before left."""
    b, rows = wedge.half(spark, sf_dir), []
    pairs, asg = written(adjacency.full(b.leaves, DOM)), written(wedge.inherited(b))
    for k in range(5):
        new = written(diffusion.balance(asg, pairs, P, 1))
        row = metrics.max_load(new, P).join(moved_between(asg, new)).first()
        rows.append((k, row["max_load"], row["ratio"], row["moved_weight"]))
        asg = new
    return spark.createDataFrame(rows, "call int, max_load long, ratio double, moved_weight long")
