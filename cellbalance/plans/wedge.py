"""Wedge workloads on lineitem: domain, trees, adjacency, balancers, measures."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellbalance.operators import adjacency, baselines, diffusion, domain, estimate, graphpart, metrics, octree, related, sfc, weights
from cellbalance.operators.domain import Domain
from cellbalance.operators.octree import CELL
from cellbalance.plans import sqltext as q
from cellbalance.catalog import query, table

DOM = Domain((4, 4, 1), 2)
P, EIGHTH, HALF = 128, 512, 1024
BITS, DEEP = DOM.key_bits, DOM.max_level
LEAF = f"select {q.CELL}, cast(w as bigint) as weight"


def cloud(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem as lattice points: price in cents, part, ship day."""
    li = table(spark, sf_dir, "lineitem").select(
        F.round(F.col("l_extendedprice") * 100).cast("long").alias("x"), F.col("l_partkey").cast("long").alias("y"), F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("long").alias("z")
    )
    return domain.quantize(li, ("x", "y", "z")).select("gx", "gy", "gz")


def wedge(spark: SparkSession, sf_dir: str, limit: int) -> DataFrame:
    return cloud(spark, sf_dir).filter(F.col("gx") + F.col("gy") < limit)


def slabs(points: DataFrame, dom: Domain, s: int) -> tuple[DataFrame, Domain]:
    """s copies of the points along z, in a box s roots longer."""
    side = dom.side[2]
    copies = points.withColumn("slab", F.explode(F.sequence(F.lit(0), F.lit(s - 1)))).withColumn("gz", F.col("gz") + F.col("slab") * side)
    return copies.drop("slab"), Domain((dom.roots[0], dom.roots[1], dom.roots[2] * s), dom.max_level, (*dom.side[:2], side * s))


@dataclass
class Built:
    points: DataFrame
    pyr: DataFrame
    start: DataFrame
    raw: DataFrame
    leaves: DataFrame
    dom: Domain
    p: int


def build(spark: SparkSession, points: DataFrame, dom: Domain = DOM, p: int = P, kept: bool = True) -> Built:
    """Weights, one pass of split and merge from depth 1, closure. `kept` writes the small leaf tables."""
    keep = diffusion.written if kept else (lambda df: df)
    pyr = keep(octree.pyramid(points, dom))
    start = octree.weighed(octree.uniform(spark, dom, 1), pyr)
    raw = keep(octree.adapt(start, pyr, dom, p))
    return Built(points, pyr, start, raw, keep(octree.closed_leaves(spark, raw, pyr, dom)), dom, p)


def half(spark: SparkSession, sf_dir: str, kept: bool = True) -> Built:
    return build(spark, wedge(spark, sf_dir, HALF), kept=kept)


# --- domain and tree


@query("box_bounds_lineitem", f"with {q.CLOUD} select xl as x_lo, xh as x_hi, yl as y_lo, yh as y_hi, zl as z_lo, zh as z_hi from box")
def box_bounds(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select(F.round(F.col("l_extendedprice") * 100).cast("long").alias("x"), F.col("l_partkey").alias("y"), F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("z"))
    return domain.bounds(li, ("x", "y", "z"))


@query("lattice_lineitem", f"with {q.CLOUD} select gx, gy, gz, count(*) as cnt from cloud group by all")
def lattice(spark, sf_dir):
    return cloud(spark, sf_dir).groupBy("gx", "gy", "gz").agg(F.count("*").alias("cnt"))


@query("root_grid", "select cast(0 as integer) as level, a.i as cx, b.i as cy, cast(0 as bigint) as cz from range(0, 4) a(i), range(0, 4) b(i)")
def root_grid(spark, sf_dir):
    return domain.roots(spark, DOM)


@query("uniform_leaves", "select cast(1 as integer) as level, a.i as cx, b.i as cy, c.i as cz from range(0, 8) a(i), range(0, 8) b(i), range(0, 2) c(i)")
def uniform_leaves(spark, sf_dir):
    return octree.uniform(spark, DOM, 1)


@query("split_children", "select cast(1 as integer) as level, a.i as cx, b.i as cy, c.i as cz from range(0, 8) a(i), range(0, 8) b(i), range(0, 2) c(i)")
def split_children(spark, sf_dir):
    return octree.split(domain.roots(spark, DOM))


@query("merge_siblings", f"with {q.wedge(EIGHTH)} select cast(0 as integer) as level, cx, cy, cz, cast(0 as bigint) as weight from merged")
def merge_siblings(spark, sf_dir):
    return octree.merge(build(spark, wedge(spark, sf_dir, EIGHTH)).start)


@query("cell_pyramid_lineitem", f"with {q.wedge(None)} {LEAF} from pyr")
def cell_pyramid(spark, sf_dir):
    return octree.pyramid(cloud(spark, sf_dir), DOM)


_TREE = f"""with {q.wedge(None)},
inner_ as (select pyr.* from pyr, tot where w * 32 > t and lv < 2),
nodes as (select 0 lv, cx, cy, cz from roots union all select lv + 1, 2 * cx + ox, 2 * cy + oy, 2 * cz + oz from inner_, octants)
select cast(n.lv as integer) as level, n.cx, n.cy, n.cz, cast(coalesce(p.w, 0) as bigint) as weight from nodes n
left join pyr p on p.lv = n.lv and p.cx = n.cx and p.cy = n.cy and p.cz = n.cz
where not exists (select 1 from inner_ i where i.lv = n.lv and i.cx = n.cx and i.cy = n.cy and i.cz = n.cz)"""


@query("adaptive_leaves_lineitem", _TREE)
def adaptive_leaves(spark, sf_dir):
    return octree.adaptive(spark, octree.pyramid(cloud(spark, sf_dir), DOM), DOM, 32)


@query("wedge_eighth_leaves", f"with {q.wedge(EIGHTH)} {LEAF} from raw")
def wedge_eighth(spark, sf_dir):
    return build(spark, wedge(spark, sf_dir, EIGHTH)).raw


@query("wedge_half_leaves", f"with {q.wedge(HALF)} {LEAF} from raw")
def wedge_half(spark, sf_dir):
    return build(spark, wedge(spark, sf_dir, HALF)).raw


for _mode, _sql in (
    ("refine", "select 1 lv, n1.cx, n1.cy, n1.cz, n1.w from n1 where not exists (select 1 from hot h where h.cx = n1.cx and h.cy = n1.cy and h.cz = n1.cz) union all select lv, cx, cy, cz, w from raw where lv = 2"),
    ("coarsen", "select 0 lv, cx, cy, cz, 0 w from merged union all select 1, n1.cx, n1.cy, n1.cz, n1.w from n1 where not exists (select 1 from merged m where m.cx = n1.cx >> 1 and m.cy = n1.cy >> 1 and m.cz = n1.cz >> 1)"),
):

    @query(f"adapt_{_mode}_only", f"with {q.wedge(EIGHTH)}, out_ as ({_sql}) {LEAF} from out_")
    def adapt_mode(spark, sf_dir, mode=_mode):
        b = build(spark, wedge(spark, sf_dir, EIGHTH))
        return octree.adapt(b.start, b.pyr, DOM, P, mode)


@query("two_to_one_closed_leaves", f"with {q.wedge(EIGHTH)} {LEAF} from leaves")
def closed_leaves(spark, sf_dir):
    return build(spark, wedge(spark, sf_dir, EIGHTH), kept=True).leaves


@query("two_to_one_violations", f"with {q.wedge(EIGHTH)}, {q.touching('raw', DEEP)} select {q.PAIR} from touch where abs(la - lb) >= 2")
def two_to_one_violations(spark, sf_dir):
    return adjacency.violations(build(spark, wedge(spark, sf_dir, EIGHTH), kept=True).raw, DOM)


@query("two_to_one_violations_closed", f"with {q.wedge(EIGHTH)}, {q.touching('leaves', DEEP)} select {q.PAIR} from touch where abs(la - lb) >= 2")
def no_violations(spark, sf_dir):
    return adjacency.violations(build(spark, wedge(spark, sf_dir, EIGHTH), kept=True).leaves, DOM)


_FACES = f"{q.touching('leaves', DEEP)}, faces as (select *, greatest(ox, 1) * greatest(oy, 1) * greatest(oz, 1) area from touch where (ox = 0)::int + (oy = 0)::int + (oz = 0)::int = 1)"


@query("face_edges", f"with {q.wedge(HALF)}, {_FACES} select {q.PAIR}, cast(area as bigint) as area from faces")
def face_edges(spark, sf_dir):
    return adjacency.faces(half(spark, sf_dir).leaves, DOM)


@query("full_stencil_pairs", f"with {q.wedge(HALF)}, {q.touching('leaves', DEEP)} select {q.PAIR} from touch")
def full_stencil(spark, sf_dir):
    return adjacency.full(half(spark, sf_dir).leaves, DOM)


@query("locate_lineitem", f"with {q.wedge(HALF)} select gx, gy, gz, cast(lv as integer) as level, cx, cy, cz, count(*) as cnt from pts join leaves on gx >> (8 - lv) = cx and gy >> (8 - lv) = cy and gz >> (10 - lv) = cz group by all")
def locate_lineitem(spark, sf_dir):
    b = half(spark, sf_dir)
    return octree.locate(b.points, b.leaves, DOM).groupBy("gx", "gy", "gz", *CELL).agg(F.count("*").alias("cnt"))


# --- weights


@query("weight_particles", f"with {q.wedge(HALF)} {LEAF} from leaves where w > 0")
def weight_particles(spark, sf_dir):
    b = half(spark, sf_dir)
    return weights.particles(octree.locate(b.points, b.leaves, DOM))


@query("weight_estimated_contacts", f"with {q.wedge(HALF)} select {q.CELL}, cast(w * 6 as bigint) as weight from leaves")
def weight_estimated(spark, sf_dir):
    return half(spark, sf_dir).leaves.withColumn("weight", weights.estimated_contacts(F.col("weight")))


@query("interface_area", f"with {q.wedge(HALF)}, {_FACES}, sides as (select la lv, ax cx, ay cy, az cz, area from faces union all select lb, bx, by_, bz, area from faces) select {q.CELL}, cast(sum(area) as bigint) as area from sides group by lv, cx, cy, cz")
def interface_area(spark, sf_dir):
    return weights.interface_area(adjacency.faces(half(spark, sf_dir).leaves, DOM)).withColumn("level", F.col("level").cast("int"))


def _ranked(kind: str) -> str:
    return f"{q.wedge(HALF)}, {getattr(q, kind)('leaves', DEEP, BITS)}, {q.midpoint('keyed', P)}"


_CUT = f"""{_FACES}, ends as (select faces.*, s.r rs, d.r rd from faces join asg s on s.lv = la and s.cx = ax and s.cy = ay and s.cz = az
  join asg d on d.lv = lb and d.cx = bx and d.cy = by_ and d.cz = bz)"""


@query("comm_per_rank", f"with {_ranked('hilbert')}, {_CUT} select r as rank_id, cast(sum(area) as bigint) as comm from (select rs r, area from ends where rs <> rd union all select rd, area from ends where rs <> rd) group by r")
def comm_per_rank(spark, sf_dir):
    b = half(spark, sf_dir)
    return weights.comm_per_rank(adjacency.faces(b.leaves, DOM), sfc.balance(b.leaves, DOM, P, "hilbert"))


# --- curves

for _curve in ("morton", "hilbert"):

    @query(f"{_curve}_keys", f"with {q.wedge(HALF)}, {getattr(q, _curve)('leaves', DEEP, BITS)} select {q.CELL}, cast(k as bigint) as curve_key from keyed")
    def keys(spark, sf_dir, curve=_curve):
        return sfc.keyed(half(spark, sf_dir).leaves, DOM, curve).select(*CELL, "curve_key")

    @query(f"{_curve}_midpoint_assign", f"with {_ranked(_curve)} select {q.CELL}, cast(w as bigint) as weight, r as rank_id from asg")
    def midpoint_assign(spark, sf_dir, curve=_curve):
        return sfc.balance(half(spark, sf_dir).leaves, DOM, P, curve)

    @query(f"{_curve}_greedy_assign")
    def greedy_assign(spark, sf_dir, curve=_curve):
        return sfc.balance(half(spark, sf_dir).leaves, DOM, 16, curve, "greedy")

    @query(f"{_curve}_optimal_assign")
    def optimal_assign(spark, sf_dir, curve=_curve):
        return sfc.balance(half(spark, sf_dir).leaves, DOM, 16, curve, "optimal")


@query(
    "curve_adjacency_share",
    f"with {q.CLOUD}, cells as (select distinct 0 lv, gx >> 7 cx, gy >> 7 cy, gz >> 7 cz from cloud), "
    + q.morton("cells", 0, 3, "m") + ", " + q.hilbert("cells", 0, 3, "h")
    + ", both_ as (select 'morton' curve, * from m union all select 'hilbert', * from h), steps as (select curve, abs(cx - lag(cx) over w) + abs(cy - lag(cy) over w) + abs(cz - lag(cz) over w) d from both_ window w as (partition by curve order by k)) "
    "select curve, count(*) as steps, cast(sum(case when d = 1 then 1 else 0 end) as bigint) as adjacent from steps where d is not null group by curve",
)
def curve_adjacency(spark, sf_dir):
    from pyspark.sql import Window

    """Steps of both curves along the occupied cells of a grid of eight a side, and those between neighbours."""
    dom = Domain((1, 1, 1), 3)
    cells, out = octree.written(cloud(spark, sf_dir).select(F.lit(3).alias("level"), *domain.cell_of(dom, 3)).distinct()), None
    for curve in ("morton", "hilbert"):
        one = sfc.keyed(cells, dom, curve).withColumn("curve", F.lit(curve))
        out = one if out is None else out.union(one)
    w = Window.partitionBy("curve").orderBy("curve_key")
    d = sum((F.abs(F.col(c) - F.lag(c).over(w)) for c in CELL[1:]), F.lit(0))
    return out.withColumn("d", d).filter("d is not null").groupBy("curve").agg(F.count("*").alias("steps"), F.sum((F.col("d") == 1).cast("long")).alias("adjacent"))


@query("curve_count_assign", f"with {q.wedge(HALF)}, {q.hilbert('leaves', DEEP, BITS)} select {q.CELL}, cast(w as bigint) as weight, cast((row_number() over (order by k) - 1) * {P} // count(*) over () as bigint) as rank_id from keyed")
def curve_count(spark, sf_dir):
    return sfc.balance(half(spark, sf_dir).leaves, DOM, P, "hilbert", "count")


# --- baselines


@query("static_assign", f"with {q.wedge(HALF)} select cast(1 as integer) as level, cx, cy, cz, cast(w as bigint) as weight, cast(row_number() over (order by cx, cy, cz) - 1 as bigint) as rank_id from n1")
def static_assign(spark, sf_dir):
    return baselines.one_to_one(half(spark, sf_dir).start)


@query("round_robin_assign", f"with {q.wedge(HALF)} select {q.CELL}, cast(w as bigint) as weight, cast((row_number() over (order by lv, cx, cy, cz) - 1) % {P} as bigint) as rank_id from leaves")
def round_robin(spark, sf_dir):
    return baselines.round_robin(half(spark, sf_dir).leaves, P)


@query("hash_assign")
def hash_assign(spark, sf_dir):
    return baselines.hashed(half(spark, sf_dir).leaves, P)


@query("largest_first_assign")
def largest_first(spark, sf_dir):
    return baselines.largest_first(half(spark, sf_dir).leaves, P)


# --- diffusion: parents' ranks are inherited, then rounds


def inherited(b: Built) -> DataFrame:
    """The static start carried to the closed leaves: children keep the parent's rank, a merged cell
    goes to the rank with most of its weight, then the smallest."""
    old = baselines.one_to_one(b.start).select(*CELL, "weight", "rank_id")
    at1 = b.leaves.filter("level >= 1").withColumns({f"p{c}": F.expr(f"shiftright({c}, level - 1)") for c in CELL[1:]})
    down = at1.join(old.select(*[F.col(c).alias(f"p{c}") for c in CELL[1:]], "rank_id"), [f"p{c}" for c in CELL[1:]]).select(*CELL, "weight", "rank_id")
    up = old.groupBy(*[F.shiftright(c, 1).alias(c) for c in CELL[1:]]).agg(F.max_by("rank_id", F.struct("weight", -F.col("rank_id"))).alias("rank_id"))
    return down.union(b.leaves.filter("level = 0").join(up, CELL[1:]).select(*CELL, "weight", "rank_id"))


def _diffused(rounds: int) -> str:
    parts = [
        q.wedge(HALF), q.touching("leaves", DEEP),
        "old_ as (select cx, cy, cz, w, row_number() over (order by cx, cy, cz) - 1 r from n1)",
        "up_ as (select cx, cy, cz, r from (select cx >> 1 cx, cy >> 1 cy, cz >> 1 cz, r, row_number() over (partition by cx >> 1, cy >> 1, cz >> 1 order by w desc, r) n from old_) where n = 1)",
        "st0 as materialized (select l.lv, l.cx, l.cy, l.cz, l.w, o.r, (cast(l.lv as bigint) << 57) + (l.cx << 38) + (l.cy << 19) + l.cz id from leaves l join old_ o on l.lv >= 1 and o.cx = l.cx >> (l.lv - 1) and o.cy = l.cy >> (l.lv - 1) and o.cz = l.cz >> (l.lv - 1) "
        "union all select l.lv, l.cx, l.cy, l.cz, l.w, u.r, (l.cx << 38) + (l.cy << 19) + l.cz from leaves l join up_ u on l.lv = 0 and u.cx = l.cx and u.cy = l.cy and u.cz = l.cz)",
        "one_way as (select (cast(la as bigint) << 57) + (ax << 38) + (ay << 19) + az a, (cast(lb as bigint) << 57) + (bx << 38) + (by_ << 19) + bz b from touch)",
        "arcs as materialized (select a, b from one_way union all select b, a from one_way)",
    ]
    for k in range(rounds):
        s = f"st{k}"
        parts += [
            f"ld{k} as (select i.i r, coalesce(sum(w), 0) load from range(0, {P}) i(i) left join {s} on {s}.r = i.i group by i.i)",
            f"re{k} as (select distinct x.r ra, y.r rb from arcs join {s} x on x.id = a join {s} y on y.id = b where x.r <> y.r)",
            f"dg{k} as (select ra, count(*) d from re{k} group by ra)",
            f"fl{k} as (select e.ra, e.rb, la_.load la_, lb_.load lb_, (la_.load - lb_.load) // (1 + greatest(da.d, db.d)) flow from re{k} e join ld{k} la_ on la_.r = e.ra join ld{k} lb_ on lb_.r = e.rb join dg{k} da on da.ra = e.ra join dg{k} db on db.ra = e.rb where la_.load > lb_.load)",
            f"op{k} as (select distinct x.id, x.w, f.ra, f.rb, f.la_, f.lb_, f.flow from arcs join {s} x on x.id = a and x.w > 0 join {s} y on y.id = b join fl{k} f on f.ra = x.r and f.rb = y.r)",
            f"ch{k} as (select * from (select *, row_number() over (partition by id order by lb_, rb) n from op{k}) where n = 1)",
            f"qu{k} as (select * from (select id, w, ra, rb, la_, lb_, flow, row_number() over (partition by ra, rb order by w desc, id) n, sum(w) over (partition by ra, rb order by w desc, id rows between unbounded preceding and current row) s from ch{k}) where s <= flow or (n = 1 and lb_ + w < la_))",
            f"mv{k} as (select id, rb from (select *, sum(w) over (partition by rb order by flow desc, ra, n rows between unbounded preceding and current row) i from qu{k}) where lb_ + i < la_)",
            f"st{k + 1} as materialized (select {s}.lv, {s}.cx, {s}.cy, {s}.cz, {s}.w, coalesce(m.rb, {s}.r) r, {s}.id from {s} left join mv{k} m on m.id = {s}.id)",
        ]
    return "with " + ",\n".join(parts) + f" select {q.CELL}, cast(w as bigint) as weight, cast(r as bigint) as rank_id from st{rounds}"


def diffused(spark, sf_dir, **kwargs) -> DataFrame:
    b = half(spark, sf_dir)
    return diffusion.balance(inherited(b), adjacency.full(b.leaves, DOM), P, **kwargs)


@query("diffusion_round_1", _diffused(1))
def diffusion_1(spark, sf_dir):
    return diffused(spark, sf_dir, iters=1)


@query("diffusion_k_rounds", _diffused(3))
def diffusion_k(spark, sf_dir):
    return diffused(spark, sf_dir, iters=3)


for _name, _kw in (
    ("diffusion_ten_rounds", {"iters": 10}),
    ("diffusion_second_order", {"iters": 4, "scheme": "second_order"}),
    ("diffusion_pull", {"iters": 4, "direction": "pull"}),
    ("diffusion_alternate", {"iters": 4, "direction": "alternate"}),
    ("diffusion_locality", {"iters": 4, "pick": "locality"}),
    ("diffusion_tolerance", {"iters": 8, "tol": 0.6}),
):

    @query(_name)
    def diffusion_variant(spark, sf_dir, kw=_kw):
        return diffused(spark, sf_dir, **kw)


@query("rank_edges", f"with {_ranked('hilbert')}, {q.touching('leaves', DEEP)} select distinct r as rank_a, r2 as rank_b from (select s.r r, d.r r2 from touch join asg s on s.lv = la and s.cx = ax and s.cy = ay and s.cz = az join asg d on d.lv = lb and d.cx = bx and d.cy = by_ and d.cz = bz where s.r <> d.r union all select d.r, s.r from touch join asg s on s.lv = la and s.cx = ax and s.cy = ay and s.cz = az join asg d on d.lv = lb and d.cx = bx and d.cy = by_ and d.cz = bz where s.r <> d.r)")
def rank_edges(spark, sf_dir):
    b = half(spark, sf_dir)
    state = sfc.balance(b.leaves, DOM, P).withColumn("leaf", octree.leaf_id())
    return diffusion.rank_edges(state, diffusion.graph(state, adjacency.full(b.leaves, DOM)))


# --- graph partitioning of the leaf graph


def leaf_graph(b: Built) -> tuple[DataFrame, DataFrame]:
    v = diffusion.written(b.leaves.select(octree.leaf_id().alias("v"), "weight", *CELL))
    e = adjacency.faces(b.leaves, b.dom).select(F.least(diffusion.leaf_id_of("src"), diffusion.leaf_id_of("dst")).alias("a"), F.greatest(diffusion.leaf_id_of("src"), diffusion.leaf_id_of("dst")).alias("b"), "area")
    return v, diffusion.written(e)


def parts_of(asg: DataFrame) -> DataFrame:
    return asg.select(octree.leaf_id().alias("v"), F.col("rank_id").alias("part"))


def unweighted(b: Built, p: int) -> DataFrame:
    """Where diffusion and repartitioning start if p is not that of the static start: a Morton cut by count."""
    return sfc.balance(b.leaves, b.dom, p, "morton", "count")


def graph_assign(b: Built, kind: str, p: int) -> DataFrame:
    v, e = leaf_graph(b)
    vertices = v.select("v", "weight")
    if kind == "multilevel_kway":
        parts = graphpart.multilevel(vertices, e, p)
    elif kind == "sfc_seeded_kway":
        parts = graphpart.curve_seeded(vertices, e, parts_of(sfc.balance(b.leaves, b.dom, p)), p)
    else:
        old = parts_of(inherited(b)) if p == b.p else parts_of(unweighted(b, p))
        parts = graphpart.repartition(vertices, e, diffusion.written(old), p)
    return v.join(parts, "v").select(*CELL, "weight", F.col("part").alias("rank_id"))


@query("kway_leaves")
def kway(spark, sf_dir):
    return graph_assign(half(spark, sf_dir), "multilevel_kway", 32)


@query("sfc_kway_leaves")
def sfc_kway(spark, sf_dir):
    return graph_assign(half(spark, sf_dir), "sfc_seeded_kway", 32)


@query("repartition_leaves")
def repartition(spark, sf_dir):
    return graph_assign(half(spark, sf_dir), "unified_repartition", P)


# --- related decompositions on lattice cells


def _halves(source: str, axis: str, name: str, k: int = 2) -> str:
    return f"""{name}_s as (select part_id, {axis} c, sum(w) w from {source} group by all),
{name}_p as (select part_id, c, least({k - 1}, ((2 * coalesce(sum(w) over (partition by part_id order by c rows between unbounded preceding and 1 preceding), 0) + w) * {k}) // (2 * sum(w) over (partition by part_id))) s from {name}_s),
{name} as (select gx, gy, gz, w, {source}.part_id * {k} + s part_id from {source} join {name}_p on {name}_p.part_id = {source}.part_id and c = {axis})"""


_CELLS = f"{q.CLOUD}, pts as (select * from cloud where gx + gy < {HALF}), d0 as (select gx, gy, gz, count(*) w, cast(0 as bigint) part_id from pts group by all)"
_PARTS = "select cast(part_id as bigint) as part_id, count(*) as cells, cast(sum(w) as bigint) as weight from {} group by part_id"


def by_part(df: DataFrame) -> DataFrame:
    return df.groupBy("part_id").agg(F.count("*").alias("cells"), F.sum("weight").alias("weight"))


@query("rcb_lineitem", f"with {_CELLS}, " + ", ".join(_halves(f"d{i}", ("gx", "gy", "gz")[i % 3], f"d{i + 1}") for i in range(5)) + " " + _PARTS.format("d5"))
def rcb(spark, sf_dir):
    return by_part(related.rcb(related.columns_of(wedge(spark, sf_dir, HALF)), 5))


@query("orthogonal_bisection_lineitem")
def orb(spark, sf_dir):
    return by_part(related.rcb(related.columns_of(wedge(spark, sf_dir, HALF)), 5, "longest"))


@query("kdtree_lineitem")
def kdtree(spark, sf_dir):
    cells = octree.pyramid(wedge(spark, sf_dir, HALF), DOM).filter("level = 2").select(*[F.col(f"c{n}").alias(f"g{n}") for n in "xyz"], "weight")
    return by_part(related.kdtree(cells, 4))


@query("multisection_lineitem", f"with {_CELLS}, {_halves('d0', 'gx', 'd1', 4)}, {_halves('d1', 'gy', 'd2', 4)}, {_halves('d2', 'gz', 'd3', 2)} " + _PARTS.format("d3"))
def multisection(spark, sf_dir):
    return by_part(related.multisection(related.columns_of(wedge(spark, sf_dir, HALF)), (4, 4, 2)))


@query("deformed_planes_lineitem")
def deformed(spark, sf_dir):
    cells = related.columns_of(wedge(spark, sf_dir, HALF))
    planes = related.deform(cells, [256, 512, 768], "gx")
    return by_part(cells.withColumn("part_id", sum(((F.col("gx") >= x).cast("long") for x in planes), F.lit(0).cast("long"))))


# --- measures

_ALGOS = ("static", "morton", "hilbert", "round_robin")


def _loads_sql() -> str:
    parts = [q.wedge(HALF), q.morton("leaves", DEEP, BITS, "mk"), q.midpoint("mk", P, "ma"), q.hilbert("leaves", DEEP, BITS, "hk"), q.midpoint("hk", P, "ha")]
    parts += ["sa as (select w, row_number() over (order by cx, cy, cz) - 1 r from n1)", f"ra as (select w, (row_number() over (order by lv, cx, cy, cz) - 1) % {P} r from leaves)"]
    parts += [q.loads(t, P, f"l{t}") for t in ("sa", "ma", "ha", "ra")]
    parts.append("all_ as (" + " union all ".join(f"select '{a}' algo, load from l{t}" for a, t in zip(_ALGOS, ("sa", "ma", "ha", "ra"), strict=True)) + ")")
    return "with " + ",\n".join(parts)


def algo_loads(spark, sf_dir) -> list[tuple[str, DataFrame]]:
    b = half(spark, sf_dir)
    return [
        ("static", baselines.one_to_one(b.start)), ("morton", sfc.balance(b.leaves, DOM, P, "morton")),
        ("hilbert", sfc.balance(b.leaves, DOM, P, "hilbert")), ("round_robin", baselines.round_robin(b.leaves, P)),
    ]


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.union(f)
    return out


@query("max_load_per_algo", _loads_sql() + f" select algo, cast({P} as integer) as p, cast(max(load) as bigint) as max_load from all_ group by algo")
def max_load(spark, sf_dir):
    return _union([metrics.max_load(a, P).select(F.lit(n).alias("algo"), F.lit(P).alias("p"), "max_load") for n, a in algo_loads(spark, sf_dir)])


@query("imbalance_per_algo", _loads_sql() + f" select algo, cast({P} as integer) as p, cast(max(load) as bigint) as max_load, round(sum(load) / {P}.0, 6) as mean_load, round(max(load) * {P}.0 / sum(load), 6) as ratio from all_ group by algo")
def imbalance(spark, sf_dir):
    return _union([metrics.max_load(a, P).select(F.lit(n).alias("algo"), F.lit(P).alias("p"), "max_load", "mean_load", "ratio") for n, a in algo_loads(spark, sf_dir)])


@query("modelled_gain", _loads_sql() + ", tops as (select algo, max(load) m from all_ group by algo) select algo, round(cast((select m from tops where algo = 'static') as double) / m, 6) as gain from tops where algo <> 'static'")
def modelled_gain(spark, sf_dir):
    tops = _union([metrics.max_load(a, P).select(F.lit(n).alias("algo"), F.col("max_load").alias("m")) for n, a in algo_loads(spark, sf_dir)])
    before = tops.filter("algo = 'static'").select(F.col("m").alias("was"))
    return tops.filter("algo <> 'static'").join(F.broadcast(before)).select("algo", F.round(F.col("was") / F.col("m"), 6).alias("gain"))


@query("step_time_model")
def step_times(spark, sf_dir):
    b = half(spark, sf_dir)
    faces, out = diffusion.written(adjacency.faces(b.leaves, DOM)), []
    for curve in ("morton", "hilbert"):
        asg = diffusion.written(sfc.balance(b.leaves, DOM, P, curve))
        out += [metrics.step_time_model(asg, faces, P, 1.0, w).select(F.lit(curve).alias("algo"), F.lit(w).alias("comm_weight"), "step_time") for w in (0.0, 0.1, 1.0)]
    return _union(out)


def _estimate_sql(name: str, limit: int, fill: float) -> str:
    facts = f"select '{name}' workload, cast({fill} as double) fill, 1 depth, (select cast(max(w) as double) from n1) largest, (select cast(t as double) / {P} from tot) mean, (select cast(max(w) as double) from leaves) leaf"
    return f"select * from (with {q.wedge(limit)} {facts})"


_FILLS = (("medium", EIGHTH, 0.125), ("large", HALF, 0.5))


@query("apriori_estimates", f"select workload, round(largest / mean, 6) as ideal, round(largest / (mean + leaf), 6) as granular, round((1 / fill) / power(2, depth), 6) as communication from ({' union all '.join(_estimate_sql(*f) for f in _FILLS)})")
def apriori(spark, sf_dir):
    """Gains to expect of both boxes of lineitem, from the largest cell of the static start, the mean of the
    ranks and the largest leaf."""
    out = []
    for name, limit, fill in _FILLS:
        b = build(spark, wedge(spark, sf_dir, limit))
        start = b.start.agg(F.max("weight").cast("double").alias("largest"), (F.sum("weight") / F.lit(float(P))).alias("mean"))
        facts = start.join(b.leaves.agg(F.max("weight").cast("double").alias("leaf")))
        out.append(facts.select(F.lit(name).alias("workload"), F.lit(fill).alias("fill"), F.lit(1).alias("depth"), "largest", "mean", "leaf"))
    return estimate.table(_union(out))


@query("surface_ratio", "with s as (select 128 * 6 * 4 before, 1024 * 6 after) select cast(before as bigint) as before, cast(after as bigint) as after, round(cast(after as double) / before, 6) as ratio from s")
def surface_ratio(spark, sf_dir):
    one, two = (metrics.surface(octree.uniform(spark, DOM, d), DEEP) for d in (1, 2))
    both = one.select(F.col("surface").alias("before")).join(two.select(F.col("surface").alias("after")))
    return both.withColumn("ratio", F.round(F.col("after") / F.col("before"), 6))


@query("granularity", f"with {q.wedge(HALF)} select cast(max(w) as bigint) as w_max, round(cast(max(w) * {P}.0 / sum(w) as double), 6) as granularity from leaves")
def granularity(spark, sf_dir):
    return metrics.granularity(half(spark, sf_dir).leaves, P)


def _cut_sql(curve: str) -> str:
    return f"select * from (with {_ranked(curve)}, {_CUT} select '{curve}' as algo, cast({P} as integer) as p, cast(coalesce(sum(area), 0) as bigint) as cut_area, count(*) as cut_edges from ends where rs <> rd)"


@query("edge_cut_per_algo", f"{_cut_sql('morton')} union all {_cut_sql('hilbert')}")
def edge_cut(spark, sf_dir):
    b = half(spark, sf_dir)
    faces = diffusion.written(adjacency.faces(b.leaves, DOM))
    return _union([metrics.edge_cut(sfc.balance(b.leaves, DOM, P, c), faces).select(F.lit(c).alias("algo"), F.lit(P).alias("p"), "cut_area", "cut_edges") for c in ("morton", "hilbert")])


@query("edge_cut_graph")
def edge_cut_graph(spark, sf_dir):
    """Cut, moved and largest load of all six balancers at p = 32, with fragments per rank."""
    b = half(spark, sf_dir)
    faces, p, out = diffusion.written(adjacency.faces(b.leaves, DOM)), 32, []
    found = {"morton": sfc.balance(b.leaves, DOM, p, "morton"), "hilbert": sfc.balance(b.leaves, DOM, p)}
    found |= {k: graph_assign(b, k, p) for k in ("multilevel_kway", "sfc_seeded_kway", "unified_repartition")}
    found["diffusion"] = diffusion.balance(unweighted(b, p), adjacency.full(b.leaves, DOM), p, 10)
    for name, asg in found.items():
        asg = diffusion.written(asg)
        row = metrics.max_load(asg, p).join(metrics.edge_cut(asg, faces)).join(metrics.fragments(asg, faces).agg(F.max("fragments").alias("fragments")))
        out.append(row.select(F.lit(name).alias("algo"), F.lit(p).alias("p"), "max_load", "ratio", "cut_area", "fragments"))
    return _union(out)


def _locality_sql(algo: str) -> str:
    dealt = f"asg as (select *, (row_number() over (order by lv, cx, cy, cz) - 1) % {P} r from leaves)"
    placed = f"{q.wedge(HALF)}, {dealt}" if algo == "round_robin" else _ranked(algo)
    return f"select * from (with {placed}, {_CUT} select '{algo}' as algo, round(avg(cast(rs = rd as double)), 6) as inside, round(avg(case when rs <> rd then cast(abs(rs - rd) as double) end), 6) as rank_distance from ends)"


@query("locality_per_algo", " union all ".join(map(_locality_sql, ("morton", "hilbert", "round_robin"))))
def locality(spark, sf_dir):
    b = half(spark, sf_dir)
    faces = diffusion.written(adjacency.faces(b.leaves, DOM))
    return _union([metrics.locality(a, faces).withColumn("algo", F.lit(n)) for n, a in (("morton", sfc.balance(b.leaves, DOM, P, "morton")), ("hilbert", sfc.balance(b.leaves, DOM, P)), ("round_robin", baselines.round_robin(b.leaves, P)))])


@query("migration_volume", f"with {q.wedge(HALF)}, {q.morton('leaves', DEEP, BITS, 'mk')}, {q.midpoint('mk', P, 'ma')}, {q.hilbert('leaves', DEEP, BITS, 'hk')}, {q.midpoint('hk', P, 'ha')} select count(*) as moved_leaves, cast(coalesce(sum(ma.w), 0) as bigint) as moved_weight from ma join ha on ma.lv = ha.lv and ma.cx = ha.cx and ma.cy = ha.cy and ma.cz = ha.cz where ma.r <> ha.r")
def migration_volume(spark, sf_dir):
    b = half(spark, sf_dir)
    return metrics.migration_volume(sfc.balance(b.leaves, DOM, P, "morton"), sfc.balance(b.leaves, DOM, P, "hilbert"))


_PS = "ps as (select cast(power(2, i) as bigint) p from range(7, 21) r(i))"
_MODEL = f"""{q.wedge(HALF)}, {_PS}, held as (select (count(*) + {P - 1}) // {P} n from leaves), model as (
select 'morton' algo, p, p * n * 24 b from ps, held union all select 'hilbert', p, p * n * 24 from ps, held union all select 'diffusion', p, n * 24 + 416 from ps, held
union all select 'multilevel_kway', p, p * n * 880 from ps, held union all select 'sfc_seeded_kway', p, p * n * 880 from ps, held union all select 'unified_repartition', p, p * n * 440 from ps, held)"""


def process_counts(spark) -> DataFrame:
    return spark.range(7, 21).select(F.pow(F.lit(2.0), F.col("id")).cast("long").alias("p"))


def modelled_memory(spark, sf_dir) -> DataFrame:
    """The model with as many leaves a rank as the half-filled box has."""
    return metrics.memory_model(process_counts(spark), -(-half(spark, sf_dir).leaves.count() // P))


@query("memory_model", f"with {_MODEL} select algo, p, cast(b as bigint) as rank_bytes, cast(cast(b as hugeint) * p as varchar) as all_bytes from model")
def memory_model(spark, sf_dir):
    return modelled_memory(spark, sf_dir).withColumn("all_bytes", F.col("all_bytes").cast("string"))


@query("max_feasible_p", f"with {_MODEL} select algo, max(p) as max_p from model where b <= 33554432 group by algo")
def max_feasible(spark, sf_dir):
    """Nodes of 16 GiB with 64 ranks, an eighth of the memory for balancing: k-way ends first, repartitioning
    at twice as many ranks, the curves further up, diffusion nowhere."""
    return metrics.max_feasible_p(modelled_memory(spark, sf_dir), metrics.rank_budget())


def _weak_sql() -> str:
    return f"""with {q.wedge(HALF)}, sizes as (select unnest([1, 2, 4]) s),
copies as (select s, lv, cx, cy, cz + (k.i << lv) cz, w from leaves, sizes, range(0, 4) k(i) where k.i < s),
{q.morton('copies', DEEP, BITS)}, {q.midpoint('keyed', P, 'asg1', 's')},
fixed as (select s, k, w, sum(w) over (partition by s order by k rows between unbounded preceding and 1 preceding) b, sum(w) over (partition by s) t from keyed),
ranked as (select s, w, least(128 * s - 1, ((2 * coalesce(b, 0) + w) * 128 * s) // (2 * t)) r from fixed),
sums as (select s, r, sum(w) load from ranked group by all)
select cast(s as integer) as slabs, cast(128 * s as integer) as p, cast(max(load) as bigint) as max_load from sums group by s"""


@query("weak_scaling_table", _weak_sql())
def weak_scaling(spark, sf_dir):
    """Largest load of the Morton cut as the wedge grows along z, 128 ranks a slab."""
    points, out = wedge(spark, sf_dir, HALF), []
    for s in (1, 2, 4):
        copies, dom = slabs(points, DOM, s)
        b = build(spark, copies, dom, P * s, kept=True)
        out.append(metrics.max_load(sfc.balance(b.leaves, dom, P * s, "morton"), P * s).select(F.lit(s).alias("slabs"), F.lit(P * s).alias("p"), "max_load"))
    return _union(out)


@query("million_ranks")
def million_ranks(spark, sf_dir):
    """The largest size of the sweep on leaves alone: 8192 slabs of the half-filled wedge's leaves."""
    b, s = half(spark, sf_dir), 8192
    dom = Domain((4, 4, s), DEEP, (1024, 1024, 1024 * s))
    leaves = b.leaves.withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(s - 1).cast("long")))).withColumn("cz", F.col("cz") + F.expr("shiftleft(k, level)")).drop("k")
    return metrics.max_load(sfc.balance(leaves, dom, P * s, "morton"), P * s)


@query("pipeline_migration")
def pipeline_migration(spark, sf_dir):
    """The whole pipeline from the static start: what moves once leaves are adapted and cut anew."""
    b = half(spark, sf_dir)
    return metrics.migration(inherited(b), sfc.balance(b.leaves, DOM, P))


def hilbert_assignment(spark, sf_dir):
    return sfc.balance(half(spark, sf_dir).leaves, DOM, P)
