"""DuckDB SQL that checks the queries: other algorithms than ours, on the same tables.

win: one window of size s stands for a chain of s filters. recursion: synchronous geodesic
filters, which also give the chain length. reach: threshold sets grown from the marker, one
level at a time. They share nothing with the kernels.
"""

from __future__ import annotations


def win(src: str, s: int, op: str = "min", axes: tuple[str, ...] = ("x", "y"), others: tuple[str, ...] = ("img", "y", "x"), keep: str = "") -> str:
    """Window extremum of half side s along the axes; keep: further columns that are passed on."""
    coordinates = ", ".join(others)
    for axis in axes:
        rest = ", ".join(c for c in others if c != axis)
        src = f"(select {coordinates}, {op}(v) over (partition by {rest} order by {axis} range between {s} preceding and {s} following) v{keep} from {src})"
    return src


def opening(src: str, s: int) -> str:
    return win(win(src, s, "min"), s, "max")


def closing(src: str, s: int) -> str:
    return win(win(src, s, "max"), s, "min")


def asf(src: str, s: int, first: str = "open") -> str:
    for k in range(1, s + 1):
        src = closing(opening(src, k), k) if first == "open" else opening(closing(src, k), k)
    return src


def recursion(start: str, by: str = "dilation", cap: int | None = None) -> str:
    """start: select of img, y, x, v (marker), m (mask). Rows (img, y, x, v, k): the fixed point and the filters that changed the image."""
    op, clamp = ("max", "least") if by == "dilation" else ("min", "greatest")
    limit = f" and k < {cap}" if cap is not None else ""
    step = f"select k, img, y, x, v, m, {op}(h) over (partition by img, x order by y rows between 1 preceding and 1 following) n from (select *, {op}(v) over (partition by img, y order by x rows between 1 preceding and 1 following) h from r where changed{limit})"
    return f"""(with recursive r as (select 0 k, img, y, x, v, m, true changed from {start}
      union all select k + 1, img, y, x, {clamp}(n, m), m, bool_or({clamp}(n, m) <> v) over (partition by img) from ({step}))
      , t as (select img, max(k) k, max(case when changed then k else 0 end) changes from r group by img)
      select img, y, x, v, m, t.changes k from r join t using (img, k))"""


def reach(start: str) -> str:
    """Reconstruction by dilation of whole-numbered images: the highest level at which a pixel is reached. start has v <= m."""
    return f"""(with recursive p as (select img, y, x, v, m from {start}), l as (select img, v t from p union select img, m from p)
      , r as (select p.img, y, x, t from p join l on l.img = p.img and p.v >= t
        union select p.img, p.y, p.x, r.t from r, unnest([-1, 0, 1]) a(dy), unnest([-1, 0, 1]) b(dx), p where p.img = r.img and p.y = r.y + dy and p.x = r.x + dx and p.m >= r.t)
      select img, y, x, max(t) v from r group by all)"""


def marked(src: str, v: str) -> str:
    """src with v as mask m and a marker computed from it."""
    return f"(select img, y, x, {v} v, v m from {src})"


EDGE = "y = 0 or x = 0 or y = max(y) over (partition by img) or x = max(x) over (partition by img)"


def border(src: str, inside: str) -> str:
    return marked(src, f"case when {EDGE} then v else {inside}(v) over (partition by img) end")


def negated(src: str, extra: str = "") -> str:
    return f"(select img, y, x, -v v{extra} from {src})"


def levels(src: str, sizes: range, family: str = "open") -> str:
    """(img, s, v sum) of openings (closings) of the sizes."""
    op = opening if family == "open" else closing
    parts = [f"select img, {s}::int s, sum(v) g from {op(src, s) if s else src} group by img" for s in sizes]
    return "(" + " union all ".join(parts) + ")"


def residual(src: str, s_max: int) -> str:
    """(img, y, x, d, r): the largest loss over window erosions, the smallest size of equal ones, counted from 1."""
    parts = [f"select img, y, x, {s} s, v from {win(src, s) if s else src}" for s in range(s_max + 1)]
    return f"""(with e as ({" union all ".join(parts)}), l as (select *, lag(v) over (partition by img, y, x order by s) - v loss from e)
      select img, y, x, coalesce(arg_max(s, loss * 100000 - s) filter (loss > 0), 0)::int d, coalesce(max(loss) filter (loss > 0), 0) r from l group by all)"""


def lipschitz(d: str, d_max: int) -> str:
    """Distance made 1-Lipschitz: the least eroded value plus size. d has v."""
    parts = [f"select img, y, x, v + {j} v from {win(d, j) if j else d}" for j in range(d_max + 1)]
    return f"(select img, y, x, min(v)::int d from ({' union all '.join(parts)}) group by all)"
