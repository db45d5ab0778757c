"""DuckDB SQL of the oracles: cubes, plans, and frames by an independent route (every pixel against every voxel's box)."""

from __future__ import annotations

from ..plans.spec import CUBES, ViewSpec, spec_of

SURVEY = """m as (select max(l_partkey) + 1 as px, max(l_suppkey) + 1 as sx from lineitem),
vox as (select (l_partkey * 40) // px as x, (l_suppkey * 40) // sx as y, (date_diff('day', date '1995-01-01', l_shipdate::date) * 18) // 2520 as z,
        sum(round(l_extendedprice * 1e2)::bigint)::bigint as v from lineitem, m group by 1, 2, 3)"""


def survey_points(dims) -> str:
    """vox(x, y, z): line items in a survey cube of some size."""
    return f"""m as (select max(l_partkey) + 1 as px, max(l_suppkey) + 1 as sx from lineitem),
vox as (select (l_partkey * {dims[0]}) // px as x, (l_suppkey * {dims[1]}) // sx as y, (date_diff('day', date '1995-01-01', l_shipdate::date) * {dims[2]}) // 2520 as z from lineitem, m)"""


WIDE = """m as (select max(user_id) + 1 as ux from events),
vox as (select (user_id * 27) // ux as x, ((hour(ts) * 60 + minute(ts)) * 27) // 1440 as y, ((day(ts) - 1) * 16) // 30 as z,
        sum(round(value * 1e2)::bigint)::bigint as v from events, m group by 1, 2, 3)"""


def cic(edge: str = "clamp", n: int = 32) -> str:
    where = {"clamp": f"greatest(0, least({n - 1}, {{}}))", "wrap": f"((({{}}) % {n}) + {n}) % {n}"}[edge]
    cells = ", ".join(where.format(f"floor(q{a} / 256e0)::bigint + c{a}") + f" as {a}" for a in "xyz")
    weight = " * ".join(f"(case c{a} when 1 then q{a} - 256 * floor(q{a} / 256e0)::bigint else 256 - q{a} + 256 * floor(q{a} / 256e0)::bigint end)" for a in "xyz")
    return f"""q as (select floor((l_quantity - 1e0) * {n}e0 / 49e0 * 256e0 + 5e-1)::bigint - 128 as qx, floor(l_extendedprice * {n}e0 / 105000e0 * 256e0 + 5e-1)::bigint - 128 as qy,
        floor(date_diff('day', date '1995-01-01', l_shipdate::date)::double * {n}e0 / 2520e0 * 256e0 + 5e-1)::bigint - 128 as qz from lineitem),
two as (select unnest([0, 1]) as c),
vox as (select x, y, z, sum(w)::bigint as v from (select {cells}, {weight} as w from q, (select c as cx from two), (select c as cy from two), (select c as cz from two)) where w <> 0 group by 1, 2, 3)"""


def scaled(base: str, k: int) -> str:
    return base.replace("vox as (", "vox0 as (") + f", r as (select unnest(range({k})) as i), vox as (select x * {k} + a.i as x, y * {k} + b.i as y, z * {k} + c.i as z, v from vox0, r a, r b, r c)"


def nearest_scaled(base: str, n: int, m: int) -> str:
    axis = f"g as (select i, ((2 * i + 1) * {n}) // {2 * m} as s from (select unnest(range({m})) as i))"
    return base.replace("vox as (", "vox0 as (") + f", {axis}, vox as (select a.i as x, b.i as y, c.i as z, v from vox0 join g a on a.s = x join g b on b.s = y join g c on c.s = z)"


VEC = """q as (select floor((embedding[1]::double + 1e0) * 16e0 * 256e0 + 5e-1)::bigint - 128 as qx, floor((embedding[2]::double + 1e0) * 16e0 * 256e0 + 5e-1)::bigint - 128 as qy, floor((embedding[3]::double + 1e0) * 16e0 * 256e0 + 5e-1)::bigint - 128 as qz from embeddings),
""" + cic().split("from lineitem),\n", 1)[1]
CUBE = {"survey": SURVEY, "wide": WIDE, "particle": cic(), "survey_scaled": scaled(SURVEY, 2), "particle_scaled": nearest_scaled(cic(), 32, 81), "vec": VEC}


def d(x: float) -> str:
    """A DOUBLE literal."""
    text = f"{float(x)!r}"
    return f"({text})" if "e" in text else f"({text}e0)"


def kd_tree(dims, n: int, axis: int | None = None) -> str:
    """leaf(brick, x0, x1, y0, y1, z0, z1): the partition rule as a recursive query."""
    ext = [f"({a}1 - {a}0)" for a in "xyz"]
    pick = str(axis) if axis is not None else f"case when {ext[0]} >= {ext[1]} and {ext[0]} >= {ext[2]} then 0 when {ext[1]} >= {ext[2]} then 1 else 2 end"
    lo = "case a when 0 then x0 when 1 then y0 else z0 end"
    size = "case a when 0 then x1 - x0 when 1 then y1 - y0 else z1 - z0 end"
    sides = []
    for s in (0, 1):
        cols = []
        for i, c in enumerate("xyz"):
            cols.append(f"case when a = {i} and {s} = 1 then cut else {c}0 end as {c}0")
            cols.append(f"case when a = {i} and {s} = 0 then cut else {c}1 end as {c}1")
        count = "lft" if s == 0 else "n - lft"
        sides.append(f"select {count} as n, path || '{s}' as path, {', '.join(cols)} from s")
    return f"""recursive t as (
  select {n} as n, '' as path, 0 as x0, {dims[0]} as x1, 0 as y0, {dims[1]} as y1, 0 as z0, {dims[2]} as z1
  union all
  (with p as (select *, {pick} as a, (1 << (length(bin(n - 1)) - 1)) as lft from t where n > 1),
        s as (select *, ({lo}) + (2 * ({size}) * lft + n) // (2 * n) as cut from p)
   {sides[0]} union all {sides[1]})),
leaf as (select (row_number() over (order by path) - 1)::int as brick, x0::int as x0, x1::int as x1, y0::int as y0, y1::int as y1, z0::int as z0, z1::int as z1 from t where n = 1)"""


IN_LEAF = "vox.x >= x0 and vox.x < x1 and vox.y >= y0 and vox.y < y1 and vox.z >= z0 and vox.z < z1"
BOX_HELD = ", ".join(f"min(vox.{a})::int as {a}0, (max(vox.{a}) + 1)::int as {a}1" for a in "xyz")


def held(dims, n: int, cube_name: str) -> str:
    """box(brick, x0, x1, y0, y1, z0, z1): what the voxels in each brick fill."""
    return f"{kd_tree(dims, n)}, {CUBE[cube_name]}, box as (select brick, {BOX_HELD} from vox join leaf on {IN_LEAF} group by brick)"


def frame_pixels(view: ViewSpec, cube_name: str) -> str:
    """px(u, v, ox, oy, oz): orthographic rays."""
    cube = spec_of(cube_name)
    s, (cx, cy, cz) = view.scale(cube), cube.centre
    right, up = f"((u + 5e-1 - {d(view.width / 2)}) / {d(s)})", f"((v + 5e-1 - {d(view.height / 2)}) / {d(s)})"
    return f"""px as (select u, v, {d(cx)} + {right} * {d(view.cos)} as ox, {d(cy)} + {up} as oy, {d(cz)} + {right} * {d(view.sin)} as oz
  from (select unnest(range({view.width}))::int as u), (select unnest(range({view.height}))::int as v))"""


def hits(view: ViewSpec, source: str = "vox") -> str:
    """hit(u, v, x, y, z, value, te, tx): each ray against the boxes of occupied voxels."""
    low, high, where = [], [], ["oy >= y and oy < y + 1"]
    for a, dd in (("x", -view.sin), ("z", view.cos)):
        if dd == 0:
            where.append(f"o{a} >= {a} and o{a} < {a} + 1")
        else:
            low.append(f"least(({a} - o{a}) / {d(dd)}, ({a} + 1 - o{a}) / {d(dd)})")
            high.append(f"greatest(({a} - o{a}) / {d(dd)}, ({a} + 1 - o{a}) / {d(dd)})")
    te, tx = f"greatest({', '.join(low)})" if len(low) > 1 else low[0], f"least({', '.join(high)})" if len(high) > 1 else high[0]
    where = [w for w in where if not w.startswith("oy")]
    extra = (" and " + " and ".join(where)) if where else ""
    return f"hit as (select u, v, x, y, z, b.v as value, {te} as te, {tx} as tx from px join (select x, y, z, v from {source}) b(x, y, z, v) on b.y = floor(px.oy)::bigint where {tx} - {te} > 1e-9{extra})".replace("px.u", "u")


def hit_cte(view: ViewSpec, cube_name: str, cube_sql: str | None = None) -> str:
    body = hits(view).replace("select u, v,", "select px.u, px.v,", 1)
    return f"{cube_sql or CUBE[cube_name]}, {frame_pixels(view, cube_name)}, {body}"


def mip(view: ViewSpec, cube_name: str, cube_sql: str | None = None) -> str:
    return f"with {hit_cte(view, cube_name, cube_sql)} select u, v, max(value)::bigint as val from hit group by u, v"


def box_hits(view: ViewSpec, boxes: str = "leaf") -> str:
    """ray(brick, u, v, te, tx): rays against brick boxes."""
    low, high, where = [], [], ["oy >= y0", "oy < y1"]
    for a, dd in (("x", -view.sin), ("z", view.cos)):
        if dd == 0:
            where += [f"o{a} >= {a}0", f"o{a} < {a}1"]
        else:
            low.append(f"least(({a}0 - o{a}) / {d(dd)}, ({a}1 - o{a}) / {d(dd)})")
            high.append(f"greatest(({a}0 - o{a}) / {d(dd)}, ({a}1 - o{a}) / {d(dd)})")
    te, tx = (f"greatest({', '.join(low)})", f"least({', '.join(high)})") if len(low) > 1 else (low[0], high[0])
    return f"ray as (select brick, u, v, {te} as te, {tx} as tx from px, {boxes} where {' and '.join(where)} and {tx} - {te} > 1e-9)"


def rects(view: ViewSpec, cube_name: str, boxes: str = "leaf", node: str = "brick") -> str:
    """rect(brick, node, u0, u1, v0, v1): corners as values."""
    m = view.matrix(CUBES[cube_name])

    def row(i):
        return f"({d(m[4 * i])} * px + {d(m[4 * i + 1])} * py + {d(m[4 * i + 2])} * pz + {d(m[4 * i + 3])})"

    w, h = view.width, view.height
    return f"""corner as (select brick, {node} as node, (case i & 1 when 1 then x1 else x0 end)::double as px, (case i >> 1 & 1 when 1 then y1 else y0 end)::double as py,
  (case i >> 2 & 1 when 1 then z1 else z0 end)::double as pz from {boxes}, (select unnest(range(8)) as i)),
prj as (select brick, node, {row(3)} as w, case when {row(3)} > 0 then {row(0)} / {row(3)} end as u, case when {row(3)} > 0 then {row(1)} / {row(3)} end as v from corner),
rect0 as (select brick, node, case when bool_and(w > 0) then greatest(floor(min(u)), 0) else 0 end::int as u0, case when bool_and(w > 0) then least(ceil(max(u)), {w}) else {w} end::int as u1,
  case when bool_and(w > 0) then greatest(floor(min(v)), 0) else 0 end::int as v0, case when bool_and(w > 0) then least(ceil(max(v)), {h}) else {h} end::int as v1 from prj group by brick, node),
rect as (select * from rect0 where u0 < u1 and v0 < v1)"""


def hits_batch(views: list[ViewSpec], cube_name: str) -> str:
    """hit(frame, u, v, x, y, z, value, te, tx) of many orthographic views on vox."""
    cube = spec_of(cube_name)
    cx, cy, cz = cube.centre
    rows = ", ".join(f"({v.frame}::bigint, {d(v.cos)}, {d(v.sin)}, {d(v.scale(cube))}, {v.width}, {v.height})" for v in views)
    slab = {a: (f"least(({a} - o{a}) / nullif(d{a}, 0), ({a} + 1 - o{a}) / nullif(d{a}, 0))", f"greatest(({a} - o{a}) / nullif(d{a}, 0), ({a} + 1 - o{a}) / nullif(d{a}, 0))") for a in "xz"}
    te, tx = f"greatest({slab['x'][0]}, {slab['z'][0]})", f"least({slab['x'][1]}, {slab['z'][1]})"
    inside = " and ".join(f"(d{a} <> 0 or (o{a} >= {a} and o{a} < {a} + 1))" for a in "xz")
    return f"""hv(frame, cs, sn, sc, w, h) as (values {rows}),
hp as (select frame, u, v, {d(cx)} + (u + 5e-1 - w / 2) / sc * cs as ox, {d(cy)} + (v + 5e-1 - h / 2) / sc as oy, {d(cz)} + (u + 5e-1 - w / 2) / sc * sn as oz, -sn as dx, cs as dz
  from (select *, unnest(range(h))::int as v from (select *, unnest(range(w))::int as u from hv))),
hit as (select hp.frame, hp.u, hp.v, b.x, b.y, b.z, b.value, {te} as te, {tx} as tx from hp join (select x, y, z, v as value from vox) b on b.y = floor(hp.oy)::bigint where {inside} and {tx} - {te} > 1e-9)"""


def rects_of_nodes(view: ViewSpec, cube_name: str, counts) -> str:
    """rect(n, brick, u0, u1, v0, v1): rectangles of the bricks of several plans."""
    dims = CUBES[cube_name].dims
    parts = " union all ".join(f"select * from (with {kd_tree(dims, n)} select {n} as n, brick, x0, x1, y0, y1, z0, z1 from leaf)" for n in counts)
    return f"boxes as ({parts}), {rects(view, cube_name, boxes='boxes', node='n')}".replace("rect as (select * from rect0", "rect as (select *, node as n from rect0")


def rects_batch(views: list[ViewSpec], cube_name: str, boxes: str = "leaf", node: str = "brick") -> str:
    """rect(frame, angle, brick, node, u0, u1, v0, v1) of many views."""
    rows = ", ".join(f"({v.frame}::bigint, {d(v.angle)}, {v.width}, {v.height}, [{', '.join(d(x) for x in v.matrix(CUBES[cube_name]))}])" for v in views)
    row = lambda i: f"(m[{4 * i + 1}] * px + m[{4 * i + 2}] * py + m[{4 * i + 3}] * pz + m[{4 * i + 4}])"
    return f"""views(frame, angle, w, h, m) as (values {rows}),
corner as (select brick, {node} as node, (case i & 1 when 1 then x1 else x0 end)::double as px, (case i >> 1 & 1 when 1 then y1 else y0 end)::double as py,
  (case i >> 2 & 1 when 1 then z1 else z0 end)::double as pz from {boxes}, (select unnest(range(8)) as i)),
prj as (select frame, angle, brick, node, w, h, {row(0)} / {row(3)} as u, {row(1)} / {row(3)} as v from corner, views),
rect0 as (select frame, angle, brick, node, greatest(floor(min(u)), 0)::int as u0, least(ceil(max(u)), w)::int as u1, greatest(floor(min(v)), 0)::int as v0, least(ceil(max(v)), h)::int as v1 from prj group by frame, angle, brick, node, w, h),
rect as (select * from rect0 where u0 < u1 and v0 < v1)"""
