"""Invariants of trees, curves and balancers on small inputs."""

import random

import pytest
from pyspark.sql import functions as F

from cellbalance.functions.curves import hilbert_automaton, hilbert_index
from cellbalance.operators import adjacency, baselines, contacts, diffusion, graphpart, metrics, octree, related, sfc
from cellbalance.operators.domain import Domain, quantize, uniform_cells
from cellbalance.plans import wedge

LEAF = "level int, cx long, cy long, cz long, weight long"


def random_leaves(spark, seed, dom):
    """A random forest with weights, by splitting leaves of the uniform depth 0."""
    rng, leaves = random.Random(seed), [(0, x, y, z) for x in range(dom.roots[0]) for y in range(dom.roots[1]) for z in range(dom.roots[2])]
    for _ in range(6):
        at = rng.randrange(len(leaves))
        level, x, y, z = leaves[at]
        if level < dom.max_level:
            leaves[at : at + 1] = [(level + 1, 2 * x + i, 2 * y + j, 2 * z + k) for i in (0, 1) for j in (0, 1) for k in (0, 1)]
    return spark.createDataFrame([(*c, rng.randrange(20)) for c in leaves], LEAF)


def test_automaton_follows_the_curve():
    digits, nexts = hilbert_automaton()
    for point in [(0, 0, 0), (5, 2, 7), (15, 15, 15), (3, 9, 12)]:
        state = key = 0
        for b in range(3, -1, -1):
            octant = sum(((v >> b) & 1) << (2 - i) for i, v in enumerate(point))
            key, state = key * 8 + digits[state * 8 + octant], nexts[state * 8 + octant]
        assert key == hilbert_index(point, 4)


@pytest.mark.parametrize("seed", [1, 2])
def test_closure_tiles_and_keeps_neighbours_within_a_level(spark, seed):
    dom = Domain((2, 1, 1), 4)
    leaves = random_leaves(spark, seed, dom)
    closed = diffusion.written(octree.leaves_of(octree.close_two_to_one(octree.interior_of(leaves, dom), dom), spark, dom).withColumn("weight", F.lit(1).cast("long")))
    assert closed.agg(F.sum(F.expr(f"shiftleft(cast(1 as bigint), 3 * ({dom.max_level} - level))"))).first()[0] == 2 * 8**dom.max_level
    assert adjacency.violations(closed, dom).count() == 0
    again = octree.leaves_of(octree.close_two_to_one(octree.interior_of(closed, dom), dom), spark, dom)
    assert again.exceptAll(closed.select(*octree.CELL)).count() == 0


@pytest.mark.parametrize("curve", ["morton", "hilbert"])
@pytest.mark.parametrize("how", ["midpoint", "greedy", "optimal", "count"])
def test_cuts_are_monotone_and_bounded(spark, curve, how):
    dom, p = Domain((2, 1, 1), 4), 5
    asg = [r for r in sfc.cut(sfc.keyed(random_leaves(spark, 3, dom), dom, curve), "curve_key", p, how).orderBy("curve_key").collect()]
    ranks = [r.rank_id for r in asg]
    assert ranks == sorted(ranks) and 0 <= min(ranks) and max(ranks) < p
    total, most = sum(r.weight for r in asg), max(r.weight for r in asg)
    load = [sum(r.weight for r in asg if r.rank_id == k) for k in range(p)]
    if how == "midpoint":
        assert max(load) <= total / p + most
    if how == "optimal":
        assert max(load) == brute_chain([r.weight for r in asg], p)
    if how == "greedy":
        assert [min(k for k, x in enumerate(ranks) if x == r) for r in sorted(set(ranks))] == greedy_starts([r.weight for r in asg], p)


def brute_chain(weights, p):
    best = [0] + [float("inf")] * len(weights)
    for _ in range(p):
        nxt = [0] + [min(max(best[i], sum(weights[i:j])) for i in range(j)) for j in range(1, len(weights) + 1)]
        best = [min(a, b) for a, b in zip(best, nxt)]
    return best[-1]


def greedy_starts(weights, p):
    """Places at which runs start if each takes rows up to the mean of what is left."""
    left, starts, load = sum(weights), [0], 0
    aim = -(-left // p)
    for k, w in enumerate(weights):
        if load + w > aim and k > starts[-1] and len(starts) < p:
            left -= load
            starts.append(k)
            load, aim = 0, -(-left // (p - len(starts) + 1))
        load += w
    return starts


def test_cuts_of_a_chain_match_plain_loops(spark):
    rng = random.Random(5)
    for weights, p in (([5, 1, 1, 1, 8, 2, 2], 3), ([rng.randrange(1, 50) for _ in range(500)], 17), ([7], 4), ([0, 0, 0], 2), ([rng.choice((1, 1, 900)) for _ in range(60)], 9)):
        rows = diffusion.written(spark.createDataFrame(list(enumerate(weights)), "pos long, weight long"))
        assert sorted(r.pos for r in sfc.run_starts(rows, "pos", p).collect()) == greedy_starts(weights, p)
        assert sfc.least_capacity(rows, "pos", p) == brute_chain(weights, p)
        for how in ("greedy", "optimal"):
            got = [r.rank_id for r in sfc.cut(rows, "pos", p, how).orderBy("pos").collect()]
            assert got == sorted(got) and got[0] == 0 and got[-1] < p
    old = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")  # runs cross batches
    try:
        weights = [rng.randrange(0, 30) for _ in range(200)]
        rows = diffusion.written(spark.createDataFrame(list(enumerate(weights)), "pos long, weight long"))
        assert sorted(r.pos for r in sfc.run_starts(rows, "pos", 13).collect()) == greedy_starts(weights, 13)
        assert sfc.least_capacity(rows, "pos", 13) == brute_chain(weights, 13)
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", old)


def test_ranges_of_a_clustered_order_hold_like_numbers_of_rows(spark):
    # nearly all keys lie in a billionth of the key range
    rows = spark.range(20_000).selectExpr("case when id < 19990 then id else 1000000000000 * (id - 19000) end as k", "cast(1 + id % 3 as long) as weight")
    held = sfc.prefix(rows, "k", "weight")
    want, before = {}, 0
    for r in sorted(rows.collect()):
        want[r.k], before = before, before + r.weight
    got = {r.k: r.before for r in held.collect()}
    assert got == want and {r.total for r in held.select("total").distinct().collect()} == {before}
    ranged = rows.repartitionByRange(8, "k").groupBy(F.spark_partition_id()).count().collect()
    assert max(r[1] for r in ranged) < 0.25 * 20_000


def test_orders_are_cut_side_by_side(spark):
    rows = spark.range(600).selectExpr("id % 3 as s", "id * 5 % 1009 as k", "1 + id % 7 as weight")
    both = {(r.s, r.k): r.rank_id for r in sfc.cut_each(rows, "s", "k", 6, 12).collect()}
    for s in range(3):
        assert {k: v for (x, k), v in both.items() if x == s} == {r.k: r.rank_id for r in sfc.cut(rows.filter(f"s = {s}"), "k", 6).collect()}


def test_box_ranges_cover_the_cells_of_the_box(spark):
    from cellbalance.functions.curves import hilbert_index

    dom = Domain((3, 2, 1), 2)
    for curve in ("morton", "hilbert"):
        ranges = sfc.ranges_for_box(dom, (1, 2, 0), (5, 5, 2), 2, curve)
        keys = {r.curve_key for r in sfc.keyed(octree.uniform(spark, dom, 2), dom, curve).filter("cx between 1 and 5 and cy between 2 and 5 and cz between 0 and 2").collect()}
        others = {r.curve_key for r in sfc.keyed(octree.uniform(spark, dom, 2), dom, curve).collect()} - keys
        inside = lambda k: any(a <= k < b for a, b in ranges)  # noqa: B023, E731
        assert all(map(inside, keys)) and not any(map(inside, others))
    assert hilbert_index((0, 0, 0), 4) == 0


def test_diffusion_never_raises_the_largest_load(spark, data):
    b = wedge.half(spark, data)
    state = wedge.inherited(b).select(octree.leaf_id().alias("leaf"), *octree.CELL, "weight", F.col("rank_id").cast("long").alias("rank_id"))
    state, edges = diffusion.written(state), None
    edges = diffusion.written(diffusion.graph(state, adjacency.full(b.leaves, wedge.DOM)))
    loads = []
    for _ in range(3):
        loads.append(metrics.max_load(state, wedge.P).first())
        state = diffusion.written(diffusion.step(state, edges, wedge.P)[0])
    loads.append(metrics.max_load(state, wedge.P).first())
    assert all(a.max_load >= b.max_load and a.total == b.total for a, b in zip(loads, loads[1:]))
    assert loads[-1].max_load < loads[0].max_load


def test_graph_parts_are_balanced_and_refinement_lowers_the_cut(spark, data):
    b = wedge.half(spark, data)
    v, e = wedge.leaf_graph(b)
    vertices = v.select("v", "weight")
    seed = diffusion.written(wedge.parts_of(sfc.balance(b.leaves, wedge.DOM, 8)))
    refined = diffusion.written(graphpart.curve_seeded(vertices, e, seed, 8))
    assert graphpart.cut_area(refined, e) <= graphpart.cut_area(seed, e)
    parts = diffusion.written(graphpart.multilevel(vertices, e, 8))
    total, most = vertices.agg(F.sum("weight"), F.max("weight")).first()
    assert parts.count() == vertices.count()
    assert vertices.join(parts, "v").groupBy("part").agg(F.sum("weight").alias("w")).agg(F.max("w")).first()[0] <= 1.05 * total / 8 + 2 * most
    renamed = parts.select("v", ((F.col("part") + 3) % 8).alias("part"))
    assert graphpart.moved_weight(graphpart.remap(renamed, parts, vertices), parts, vertices) == 0
    old = diffusion.written(wedge.parts_of(wedge.unweighted(b, 8)))
    drifted = graphpart.diffuse(vertices, e, old, 8)
    load = lambda x: vertices.join(x, "v").groupBy("part").agg(F.sum("weight").alias("w")).agg(F.max("w")).first()[0]
    assert load(drifted) < load(old) and drifted.count() == vertices.count()
    anew = diffusion.written(graphpart.repartition(vertices, e, old, 8))
    assert load(anew) < load(old) and graphpart.moved_weight(anew, old, vertices) < total


def test_lattices_have_their_coordination_numbers(spark):
    cubic = spark.range(125).select(F.col("id").alias("pid"), F.expr("cast(id div 25 as double)").alias("x"), F.expr("cast(id div 5 % 5 as double)").alias("y"), F.expr("cast(id % 5 as double)").alias("z"))
    pairs = contacts.touching_spheres(cubic, 0.5)
    both = pairs.select("pid_a").union(pairs.select("pid_b")).groupBy("pid_a").count()
    assert both.filter("pid_a = 62").first()["count"] == 6 and pairs.count() == 3 * 4 * 25


def test_buckets_find_the_brute_force_contacts(spark):
    rng = random.Random(4)
    pts = spark.createDataFrame([(i, *(rng.randrange(60) for _ in range(3))) for i in range(300)], "pid long, gx long, gy long, gz long")
    assert sorted(contacts.detect(pts, 9).collect()) == sorted(contacts.brute_force(pts, 9).collect())


def test_edges_of_the_box(spark):
    pts = spark.createDataFrame([(0, 0, 0), (9, 9, 9), (9, 9, 9), (None, 1, 1)], "x long, y long, z long")
    cells = quantize(pts, ("x", "y", "z"), None).collect()
    assert len(cells) == 3 and max(r.gx for r in cells) < 1024
    empty = quantize(pts.limit(0), ("x", "y", "z"))
    assert octree.adaptive(spark, octree.pyramid(empty, Domain((1, 1, 1), 3)), Domain((1, 1, 1), 3), 4).collect()[0].weight == 0
    one = spark.createDataFrame([(5, 5, 5)] * 40, "gx long, gy long, gz long")
    hot = octree.adaptive(spark, octree.pyramid(one, Domain((1, 1, 1), 3)), Domain((1, 1, 1), 3), 8)
    assert hot.agg(F.max("level"), F.max("weight")).first() == (3, 40)
    idle = sfc.balance(hot, Domain((1, 1, 1), 3), 100)
    assert metrics.max_load(idle, 100).first().max_load == 40
    zero = uniform_cells(spark, Domain((2, 2, 2), 1), 0).withColumn("weight", F.lit(0).cast("long"))
    assert {r.rank_id for r in sfc.balance(zero, Domain((2, 2, 2), 1), 4).collect()} == {0}


def test_largest_first_is_within_its_bound(spark):
    leaves = random_leaves(spark, 7, Domain((2, 1, 1), 4))
    total, most = leaves.agg(F.sum("weight"), F.max("weight")).first()
    assert metrics.max_load(baselines.largest_first(leaves, 4), 4).first().max_load <= total / 4 + most


def test_bisection_halves_the_weight(spark):
    cells = spark.createDataFrame([(i, i % 7, i % 5, 1) for i in range(64)], "gx long, gy long, gz long, weight long")
    loads = [r.w for r in related.rcb(cells, 1).groupBy("part_id").agg(F.sum("weight").alias("w")).collect()]
    assert loads == [32, 32]


def test_measures_of_the_applied_case(spark):
    log = spark.createDataFrame([("a", 1, 42.0), ("b", 1, 5.5)], "algo string, step long, value double")
    assert abs(metrics.gain(log.filter("algo = 'a'"), log.filter("algo = 'b'")).first().gain - 7.636364) < 1e-6


def test_a_diffusion_round_reads_the_edges_once(spark, data):
    b = wedge.half(spark, data)
    state = wedge.inherited(b).select(octree.leaf_id().alias("leaf"), "weight", "rank_id")
    edges = diffusion.written(diffusion.graph(state, adjacency.full(b.leaves, wedge.DOM)))
    moved, _ = diffusion.step(diffusion.written(state), edges, wedge.P)
    assert not set(edges.inputFiles()) & set(moved.inputFiles())
