"""SQL building blocks for the oracles: the same quantities written independently, on small tables."""

from __future__ import annotations

CLOUD = """raw_points as (select cast(round(l_extendedprice * 100) as bigint) x, cast(l_partkey as bigint) y,
  cast(date_diff('day', date '1995-01-01', cast(l_shipdate as date)) as bigint) z from lineitem),
box as (select min(x) xl, max(x) xh, min(y) yl, max(y) yh, min(z) zl, max(z) zh from raw_points),
cloud as (select (x - xl) * 1024 // (xh - xl + 1) gx, (y - yl) * 1024 // (yh - yl + 1) gy, (z - zl) * 1024 // (zh - zl + 1) gz from raw_points, box)"""

STENCIL = "stencil as (select a.i - 1 dx, b.i - 1 dy, c.i - 1 dz from range(0, 3) a(i), range(0, 3) b(i), range(0, 3) c(i) where not (a.i = 1 and b.i = 1 and c.i = 1))"


def wedge(limit: int | None, p: int = 128) -> str:
    """CTEs up to raw (one pass of split and merge) and leaves (closed): roots 4 x 4 x 1, start depth 1."""
    where = f"where gx + gy < {limit}" if limit is not None else ""
    return f"""{CLOUD},
pts as (select * from cloud {where}),
tot as (select count(*) t from pts),
pyr as (select 0 lv, gx >> 8 cx, gy >> 8 cy, gz >> 10 cz, count(*) w from pts group by all
  union all select 1, gx >> 7, gy >> 7, gz >> 9, count(*) from pts group by all
  union all select 2, gx >> 6, gy >> 6, gz >> 8, count(*) from pts group by all),
roots as (select a.i cx, b.i cy, 0 cz from range(0, 4) a(i), range(0, 4) b(i)),
n1 as (select a.i cx, b.i cy, c.i cz, coalesce(w, 0) w from range(0, 8) a(i) cross join range(0, 8) b(i) cross join range(0, 2) c(i)
  left join pyr on lv = 1 and pyr.cx = a.i and pyr.cy = b.i and pyr.cz = c.i),
hot as (select n1.* from n1, tot where w * {p} > t),
merged as (select cx >> 1 cx, cy >> 1 cy, cz >> 1 cz from n1 group by all having sum(w) = 0),
octants as (select a.i ox, b.i oy, c.i oz from range(0, 2) a(i), range(0, 2) b(i), range(0, 2) c(i)),
raw_cells as (select 0 lv, * from merged
  union all select 1, cx, cy, cz from n1 where not exists (select 1 from hot h where h.cx = n1.cx and h.cy = n1.cy and h.cz = n1.cz)
    and not exists (select 1 from merged m where m.cx = n1.cx >> 1 and m.cy = n1.cy >> 1 and m.cz = n1.cz >> 1)
  union all select 2, 2 * cx + ox, 2 * cy + oy, 2 * cz + oz from hot, octants),
raw as (select r.lv, r.cx, r.cy, r.cz, coalesce(w, 0) w from raw_cells r left join pyr on pyr.lv = r.lv and pyr.cx = r.cx and pyr.cy = r.cy and pyr.cz = r.cz),
{STENCIL},
inner0 as (select cx, cy, cz from roots where not exists (select 1 from merged m where m.cx = roots.cx and m.cy = roots.cy)
  union select (cx + dx) >> 1, (cy + dy) >> 1, (cz + dz) >> 1 from hot, stencil where cx + dx between 0 and 7 and cy + dy between 0 and 7 and cz + dz between 0 and 1),
leaf_cells as (select 0 lv, cx, cy, cz from roots where not exists (select 1 from inner0 i where i.cx = roots.cx and i.cy = roots.cy)
  union all select 1, n1.cx, n1.cy, n1.cz from n1 join inner0 i on n1.cx >> 1 = i.cx and n1.cy >> 1 = i.cy and n1.cz >> 1 = i.cz
    where not exists (select 1 from hot h where h.cx = n1.cx and h.cy = n1.cy and h.cz = n1.cz)
  union all select 2, 2 * cx + ox, 2 * cy + oy, 2 * cz + oz from hot, octants),
leaves as (select r.lv, r.cx, r.cy, r.cz, coalesce(w, 0) w from leaf_cells r left join pyr on pyr.lv = r.lv and pyr.cx = r.cx and pyr.cy = r.cy and pyr.cz = r.cz)"""


CELL = "cast(lv as integer) as level, cast(cx as bigint) as cx, cast(cy as bigint) as cy, cast(cz as bigint) as cz"


def morton(source: str, deep: int, bits: int, name: str = "keyed") -> str:
    key = " + ".join(f"((((cx << ({deep} - lv)) >> {b}) & 1) << {3 * b + 2}) + ((((cy << ({deep} - lv)) >> {b}) & 1) << {3 * b + 1}) + ((((cz << ({deep} - lv)) >> {b}) & 1) << {3 * b})" for b in range(bits))
    return f"{name} as (select *, (({key}) >> (3 * ({deep} - lv))) << (3 * ({deep} - lv)) k from {source})"


def hilbert(source: str, deep: int, bits: int, name: str = "keyed") -> str:
    """Keys by the published transpose form, one common table a bit step: swaps and inversions from the top
    bit down, then the Gray code, then the bits interleaved. The library goes another way, by an automaton."""
    shift = f"({deep} - lv)"
    steps = [f"{name}_0 as (select *, cx << {shift} h0, cy << {shift} h1, cz << {shift} h2 from {source})"]

    def put(h0: str, h1: str, h2: str, extra: str = "") -> None:
        k = len(steps)
        drop = "h0, h1, h2" + (", g" if extra == "-" else "")
        steps.append(f"{name}_{k} as (select * exclude ({drop}), {h0} h0, {h1} h1, {h2} h2{extra if extra != '-' else ''} from {name}_{k - 1})")

    for b in range(bits - 1, 0, -1):
        on, low = 1 << b, (1 << b) - 1
        put(f"case when h0 & {on} <> 0 then xor(h0, {low}) else h0 end", "h1", "h2")
        for i in (1, 2):
            swap = f"(xor(h0, h{i}) & {low})"
            first = f"case when h{i} & {on} <> 0 then xor(h0, {low}) else xor(h0, {swap}) end"
            other = f"case when h{i} & {on} <> 0 then h{i} else xor(h{i}, {swap}) end"
            put(first, other if i == 1 else "h1", other if i == 2 else "h2")
    put("h0", "xor(h1, h0)", "h2")
    put("h0", "h1", "xor(h2, h1)")
    gray = "0"
    for b in range(bits - 1, 0, -1):
        gray = f"xor({gray}, case when h2 & {1 << b} <> 0 then {(1 << b) - 1} else 0 end)"
    put("h0", "h1", "h2", f", {gray} g")
    put("xor(h0, g)", "xor(h1, g)", "xor(h2, g)", "-")
    key = " + ".join(f"(((h{i} >> {b}) & 1) << {3 * b + 2 - i})" for b in range(bits) for i in range(3))
    return ",\n".join(steps) + f",\n{name} as (select * exclude (h0, h1, h2), (({key}) >> (3 * {shift})) << (3 * {shift}) k from {name}_{len(steps) - 1})"


def midpoint(source: str, p: int, name: str = "asg", by: str = "") -> str:
    part = f"partition by {by} " if by else ""
    return f"""{name}_sums as (select *, coalesce(sum(w) over ({part}order by k rows between unbounded preceding and 1 preceding), 0) before, sum(w) over ({part.strip()}) total from {source}),
{name} as (select * exclude (before, total), cast(case when total = 0 then 0 else least({p - 1}, ((2 * before + w) * {p}) // (2 * total)) end as bigint) r from {name}_sums)"""


def loads(source: str, p: int, name: str = "loads") -> str:
    return f"{name} as (select i.i r, coalesce(sum(w), 0) load from range(0, {p}) i(i) left join {source} a on a.r = i.i group by i.i)"


def touching(source: str, deep: int, name: str = "touch") -> str:
    """Pairs of leaves whose closed boxes meet, smaller cell first; all pairs, for small tables only."""
    lo = {n: f"({{0}}.c{n} << ({deep} - {{0}}.lv))" for n in "xyz"}
    hi = {n: f"(({{0}}.c{n} + 1) << ({deep} - {{0}}.lv))" for n in "xyz"}
    meet = " and ".join(f"{lo[n].format('a')} <= {hi[n].format('b')} and {lo[n].format('b')} <= {hi[n].format('a')}" for n in "xyz")
    over = ", ".join(f"least({hi[n].format('a')}, {hi[n].format('b')}) - greatest({lo[n].format('a')}, {lo[n].format('b')}) o{n}" for n in "xyz")
    return f"""{name} as (select a.lv la, a.cx ax, a.cy ay, a.cz az, b.lv lb, b.cx bx, b.cy by_, b.cz bz, {over}
  from {source} a join {source} b on {meet} and (a.lv < b.lv or (a.lv = b.lv and (a.cx < b.cx or (a.cx = b.cx and (a.cy < b.cy or (a.cy = b.cy and a.cz < b.cz)))))))"""


PAIR = ", ".join(f"cast({a} as bigint) as {b}" for a, b in zip(("la", "ax", "ay", "az", "lb", "bx", "by_", "bz"), ("src_level", "src_x", "src_y", "src_z", "dst_level", "dst_x", "dst_y", "dst_z"), strict=True))
