"""Graph partitioning of the leaf graph: multilevel k-way, curve-seeded k-way, repartitioning.

Vertices are (v, weight), edges (a, b, area) with a < b. Coarsening matches mutual heaviest neighbours and
then pairs what is left around the same neighbour, so stars and loose vertices shrink as well; contraction
adds weights and areas. The coarsest graph of a group of at most `fan` parts is split by greedy growth in
one task, so no task or driver holds more than some thousand vertices whatever the number of parts: more
parts are reached by splitting into groups of parts first, all groups of a stage in the same plans.
Refinement moves boundary vertices under a capacity.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellbalance.operators import diffusion
from cellbalance.operators.store import written


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b", "area").union(edges.select("b", "a", "area"))


def match(vertices: DataFrame, edges: DataFrame, most: int) -> DataFrame:
    """(v, into): each vertex proposes to its heaviest neighbour, ties by a symmetric hash of the edge;
    mutual proposals that stay light enough merge. Vertices that are left pair up with others that proposed
    to the same neighbour, or with other loose ones of their group; hubs are dealt out by a hash."""
    w = vertices.select(F.col("v"), F.col("weight"))
    arcs = both_ways(edges).join(w.select(F.col("v").alias("a"), F.col("weight").alias("wa")), "a").join(w.select(F.col("v").alias("b"), F.col("weight").alias("wb")), "b")
    arcs = arcs.filter(F.col("wa") + F.col("wb") <= most)
    tie = F.xxhash64(F.least("a", "b"), F.greatest("a", "b"))
    wish = written(arcs.groupBy("a").agg(F.max_by("b", F.struct("area", tie)).alias("b")))
    mutual = wish.alias("x").join(wish.alias("y"), (F.col("x.a") == F.col("y.b")) & (F.col("x.b") == F.col("y.a"))).select(F.col("x.a").alias("v"), F.least(F.col("x.a"), F.col("x.b")).alias("into"))
    first = written(vertices.select("v", "weight", "lo").join(mutual, "v", "left"))
    loose = first.filter(f"into is null and weight * 2 <= {most}").join(wish.select(F.col("a").alias("v"), F.col("b").alias("near")), "v", "left")
    loose = loose.withColumn("near", F.coalesce("near", -1 - F.col("lo"))).withColumn("part", F.pmod(F.xxhash64("v"), F.lit(64)))
    line = Window.partitionBy("lo", "near", "part").orderBy("v")
    pairs = loose.withColumn("nth", F.row_number().over(line)).withColumn("ahead", F.lead("v").over(line)).withColumn("behind", F.lag("v").over(line))
    two = pairs.select("v", F.when(F.expr("nth % 2 = 1"), F.col("v")).otherwise(F.col("behind")).alias("hop"))
    return first.join(two, "v", "left").select("v", F.coalesce("into", "hop", "v").alias("into"))


def contract(vertices: DataFrame, edges: DataFrame, into: DataFrame) -> tuple[DataFrame, DataFrame]:
    v = vertices.join(into, "v").groupBy(F.col("into").alias("v")).agg(F.sum("weight").alias("weight"), F.first("lo").alias("lo"), F.first("n").alias("n"))
    e = edges.join(into.select(F.col("v").alias("a"), F.col("into").alias("x")), "a").join(into.select(F.col("v").alias("b"), F.col("into").alias("y")), "b")
    e = e.filter("x <> y").groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.sum("area").alias("area"))
    return v, e


def grow(vertices: list[tuple[int, int]], edges: list[tuple[int, int, int]], shares: list[int]) -> dict[int, int]:
    """Greedy growth on a small graph: each part takes the vertex tied to it most until it has its share, in
    proportion to `shares`, of what is left."""
    near, weight = defaultdict(list), dict(vertices)
    for a, b, area in edges:
        near[a].append((b, area))
        near[b].append((a, area))
    free, out, left, parts = dict.fromkeys(sorted(weight)), {}, sum(weight.values()), sum(shares)
    for part, own in enumerate(shares):
        last = part == len(shares) - 1
        share, load, pull = -(-left * own // parts), 0, defaultdict(int)
        heap: list[tuple[int, int]] = []
        while free and (load < share or last):
            while heap and (heap[0][1] not in free or -heap[0][0] != pull[heap[0][1]]):
                heapq.heappop(heap)
            v = heap[0][1] if heap else next(iter(free))
            if load and not last and load + weight[v] - share > share - load:
                break
            del free[v]
            out[v], load = part, load + weight[v]
            for u, area in near[v]:
                if u in free:
                    pull[u] += area
                    heapq.heappush(heap, (-pull[u], u))
        left, parts = left - load, parts - own
    return out


def cut_area(parts: DataFrame, edges: DataFrame) -> int:
    a, b = (parts.select(F.col("v").alias(n), F.col("part").alias(f"p{n}")) for n in "ab")
    return edges.join(a, "a").join(b, "b").filter("pa <> pb").agg(F.coalesce(F.sum("area"), F.lit(0))).first()[0]


def refine(parts: DataFrame, vertices: DataFrame, edges: DataFrame, p: int, tol: float = 1.05, passes: int = 4) -> DataFrame:
    """Moves boundary vertices to the part they are tied to most, if that lowers the cut, under a
    capacity of tol times the mean. Passes go up and down the part numbers in turn, and of touching
    vertices only local winners move, so neighbours never swap and the cut never rises."""
    total = vertices.agg(F.sum("weight")).first()[0] or 0
    limit = int(tol * total / p)
    state = written(vertices.join(parts, "v").select("v", "weight", "part"))
    arcs = written(both_ways(edges))
    for k in range(passes):
        tied = arcs.join(state.select(F.col("v").alias("b"), F.col("part").alias("to")), "b").groupBy(F.col("a").alias("v"), "to").agg(F.sum("area").alias("tie"))
        mine = tied.join(state, "v")
        own = mine.filter("to = part").select("v", F.col("tie").alias("own"))
        loads = state.groupBy("part").agg(F.sum("weight").alias("load"))
        room = loads.select(F.col("part").alias("to"), F.col("load").alias("to_load"))
        want = mine.filter("to > part" if k % 2 == 0 else "to < part").join(own, "v", "left").withColumn("gain", F.col("tie") - F.coalesce("own", F.lit(0)))
        want = want.join(room, "to").join(loads.select("part", F.col("load").alias("from_load")), "part")
        want = want.filter(f"to_load + weight <= {limit} and (gain > 0 or (gain = 0 and to_load + weight < from_load))")
        best = want.groupBy("v").agg(F.max_by(F.struct("to", "weight", "part", "to_load", "gain"), F.struct("gain", -F.col("to"))).alias("m")).select("v", "m.*")
        rival = arcs.join(best.select(F.col("v").alias("b"), F.col("gain").alias("other")), "b").groupBy(F.col("a").alias("v")).agg(F.max(F.struct("other", "b")).alias("r"))
        best = best.join(rival, "v", "left").filter("r is null or gain > r.other or (gain = r.other and v > r.b)")
        line = Window.partitionBy("to").orderBy(F.col("gain").desc(), "v").rowsBetween(Window.unboundedPreceding, 0)
        moves = best.withColumn("_in", F.sum("weight").over(line)).filter(f"to_load + _in <= {limit}").select("v", "to")
        nxt = written(state.join(moves, "v", "left").select("v", "weight", F.coalesce("to", "part").alias("part"), F.col("to").isNotNull().alias("moved")))
        state = nxt.drop("moved")
        if k % 2 and nxt.filter("moved").isEmpty():
            break
    return state.select("v", "part")


def rebalanced(parts: DataFrame, vertices: DataFrame, p: int, tol: float, rounds: int = 12) -> DataFrame:
    """Vertices of overfull parts beyond the capacity move to parts with room: in each round every such
    vertex asks one of them, dealt by a hash, and each admits by weight while it has room."""
    row = vertices.agg(F.sum("weight"), F.max("weight")).first()
    limit = int(tol * (row[0] or 0) / p) + (row[1] or 0)
    state = written(vertices.select("v", "weight").join(parts, "v").select("v", "weight", "part"))
    every = state.sparkSession.range(p).withColumnRenamed("id", "part")
    for k in range(rounds):
        line = Window.partitionBy("part").orderBy(F.col("weight").desc(), "v").rowsBetween(Window.unboundedPreceding, 0)
        over = state.withColumn("_sum", F.sum("weight").over(line)).filter(f"_sum > {limit}").select("v", "weight")
        loads = every.join(state.groupBy("part").agg(F.sum("weight").alias("load")), "part", "left").withColumn("load", F.coalesce("load", F.lit(0)))
        mean = (row[0] or 0) // p
        room = written(loads.filter(f"load <= {mean}").withColumn("nth", F.row_number().over(Window.orderBy("load", "part")) - 1))
        n = room.count()
        if not n or over.isEmpty():
            break
        ask = over.withColumn("nth", F.pmod(F.xxhash64("v", F.lit(k)), F.lit(n))).join(room.select("nth", F.col("part").alias("to"), "load"), "nth")
        queue = Window.partitionBy("to").orderBy("weight", "v").rowsBetween(Window.unboundedPreceding, 0)
        moves = ask.withColumn("_in", F.sum("weight").over(queue)).filter(f"load + _in <= {limit}").select("v", "to")
        state = written(state.join(moves, "v", "left").select("v", "weight", F.coalesce("to", "part").alias("part")))
    return state.select("v", "part")


def _children(fan: int) -> tuple:
    """Columns of a group [lo, lo + n) of parts: into how many groups it splits now. Groups above the fan
    split so that the stages are as few as the fan allows and alike in width."""
    return F.expr(f"cast(case when n <= {fan} then n else least({fan}, ceil(n / pow({fan}, ceil(ln(n) / ln({fan}) - 1e-9) - 1))) end as bigint)")


def multilevel(vertices: DataFrame, edges: DataFrame, p: int, tol: float = 1.05, fan: int = 256) -> DataFrame:
    """(v, part): stages of splitting groups of parts, until each group is one part. In a stage all groups
    are coarsened together, grown in one task each, projected back and refined."""
    v = written(vertices.select("v", "weight", F.lit(0).cast("long").alias("lo"), F.lit(p).cast("long").alias("n")))
    e = written(edges.select("a", "b", "area"))
    total, wide = v.agg(F.sum("weight")).first()[0] or 0, p
    while wide > 1:
        split = v.select("lo", "n").distinct().withColumn("k", _children(fan))
        # the groups of the next stage: each knows its first part and how many it holds
        child = split.withColumn("j", F.explode(F.expr("sequence(0, k - 1)"))).select(F.expr("lo + j * n div k").alias("part"), F.expr("(j + 1) * n div k - j * n div k").alias("n"))
        child = written(child)
        children, wide = child.agg(F.count("*"), F.coalesce(F.max("n"), F.lit(1))).first()
        ends = [v.select(F.col("v").alias(x), F.col("lo").alias(f"lo_{x}")) for x in "ab"]
        inside = written(e.join(ends[0], "a").join(ends[1], "b").filter("lo_a = lo_b").select("a", "b", "area"))
        levels, cv, ce, count = [], v, inside, v.count()
        most = max(1, -(-total // (2 * max(children, 1))))
        while count > max(4 * children, 64):
            into = written(match(cv, ce, most))
            nv, ne = (written(x) for x in contract(cv, ce, into))
            m = nv.count()
            if m > 0.95 * count:
                break
            levels.append((cv, ce, into))
            cv, ce, count = nv, ne, m
        parts = written(_grown(cv, ce, fan))
        parts = refine(parts, cv, ce, p, tol * wide)
        for fv, fe, into in reversed(levels):
            parts = into.join(parts.select(F.col("v").alias("into"), "part"), "into").select("v", "part")
            parts = refine(parts, fv, fe, p, tol * wide, passes=2)
        v = written(v.select("v", "weight").join(parts, "v").join(child, "part").select("v", "weight", F.col("part").alias("lo"), "n"))
    return rebalanced(v.select("v", F.col("lo").alias("part")), vertices, p, tol)


def _grown(vertices: DataFrame, edges: DataFrame, fan: int) -> DataFrame:
    """(v, part) of the coarsest graph: each group grown by one task; a part is named by its first number."""
    held = vertices.withColumn("k", _children(fan))
    of = edges.join(held.select(F.col("v").alias("a"), F.col("lo").alias("of")), "a").select("of", "a", "b", "area")

    def run(key: tuple, vs: pd.DataFrame, es: pd.DataFrame) -> pd.DataFrame:
        if vs.empty:
            return pd.DataFrame({"v": [], "part": []}, dtype="int64")
        lo, n, k = int(vs["lo"].iloc[0]), int(vs["n"].iloc[0]), int(vs["k"].iloc[0])
        first = [j * n // k for j in range(k + 1)]
        rows = es.sort_values(["a", "b"])[["a", "b", "area"]].itertuples(index=False, name=None)
        found = grow(sorted(vs[["v", "weight"]].itertuples(index=False, name=None)), list(rows), [b - a for a, b in zip(first, first[1:])])
        return pd.DataFrame({"v": list(found), "part": [lo + first[x] for x in found.values()]}, dtype="int64")

    return held.groupBy("lo").cogroup(of.groupBy("of")).applyInPandas(run, "v long, part long")


def curve_seeded(vertices: DataFrame, edges: DataFrame, seed: DataFrame, p: int, tol: float = 1.05) -> DataFrame:
    """A curve partition (v, part) followed by refinement."""
    return refine(seed, vertices, edges, p, tol)


def remap(new: DataFrame, old: DataFrame, vertices: DataFrame) -> DataFrame:
    """new (v, part) relabelled to overlap old most. Overlaps are taken by weight, then by number: in each
    round every pair that is the best left for both its parts is taken, which gives what taking one pair
    after another would. Parts without an overlap get the labels left over, by number."""
    new = written(new.select("v", "part"))
    both = new.join(old.select("v", F.col("part").alias("was")), "v").join(vertices.select("v", "weight"), "v")
    open_ = written(both.groupBy("part", "was").agg(F.sum("weight").alias("w")).filter("w > 0"))
    taken = None
    while not open_.isEmpty():
        by_part = open_.groupBy("part").agg(F.max_by("was", F.struct("w", -F.col("was"))).alias("was"))
        by_was = open_.groupBy("was").agg(F.max_by("part", F.struct("w", -F.col("part"))).alias("part"))
        pairs = written(by_part.join(by_was, ["part", "was"]))
        taken = pairs if taken is None else taken.union(pairs)
        open_ = written(open_.join(pairs.select("part"), "part", "left_anti").join(pairs.select("was"), "was", "left_anti"))
    parts = new.select("part").distinct()
    if taken is None:
        return new
    labels = parts.select(F.col("part").alias("was")).union(old.select(F.col("part").alias("was"))).distinct()
    line = lambda c: F.row_number().over(Window.orderBy(c))  # noqa: E731  a row for each part
    rest = parts.join(taken, "part", "left_anti").withColumn("nth", line("part")).join(labels.join(taken, "was", "left_anti").withColumn("nth", line("was")), "nth")
    named = taken.select("part", "was").union(rest.select("part", "was"))
    return new.join(named, "part").select("v", F.col("was").alias("part"))


def moved_weight(new: DataFrame, old: DataFrame, vertices: DataFrame) -> int:
    both = new.join(old.select("v", F.col("part").alias("was")), "v").filter("part <> was").join(vertices, "v")
    return both.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]


def diffuse(vertices: DataFrame, edges: DataFrame, old: DataFrame, p: int, iters: int = 10, tol: float | None = None) -> DataFrame:
    """old (v, part) after rounds of diffusion between parts that share edges of the graph."""
    state = vertices.select("v", "weight").join(old, "v").select(F.col("v").alias("leaf"), "weight", F.col("part").cast("long").alias("rank_id"))
    arcs = both_ways(edges).select(F.col("a").alias("leaf"), F.col("b").alias("other"))
    return diffusion.run(state, arcs, p, iters, tol).select(F.col("leaf").alias("v"), F.col("rank_id").alias("part"))


def repartition(vertices: DataFrame, edges: DataFrame, old: DataFrame, p: int, alpha: float = 0.1, tol: float = 1.05, iters: int = 10) -> DataFrame:
    """The better of a fresh partition remapped onto the old one and of the old one diffused over the graph
    and refined, by cut area plus alpha times the weight moved."""
    old = written(old)
    fresh = written(remap(multilevel(vertices, edges, p, tol), old, vertices))
    drifted = written(refine(diffuse(vertices, edges, old, p, iters), vertices, edges, p, tol))
    cost = [cut_area(x, edges) + alpha * moved_weight(x, old, vertices) for x in (fresh, drifted)]
    return fresh if cost[0] <= cost[1] else drifted
