"""SQL that rebuilds layers and the truth about their pairs from lineitem, by another way than the engine.

On the lattice with doubled coordinates every unit face, edge and vertex is one integer cell of dimension 2, 1 or 0. A
geometry is a set of cells with an interior flag, and a pair's matrix follows from shared and unshared cells by joins.
"""

from __future__ import annotations

from spatial_links.sources.layers import PAIRS, RECIPES, SHAPES, place_sql

BASE = """
base as (select l_orderkey * 8 + l_linenumber as gid, l_returnflag as flag, min(l_partkey // 4) as x,
  min(date_diff('day', date '1995-01-01', cast(l_shipdate as date)) // 14) as y, min(cast(l_quantity as int)) as qty,
  min(l_partkey) as pk, min(l_suppkey) as sk, min(l_linenumber) as ln, min(l_orderkey) as orderkey
  from lineitem group by l_orderkey, l_linenumber, l_returnflag having count(*) = 1)"""


def layer(name: str) -> str:
    """A CTE body: gid, x, y, w, h, shape, orderkey, is_line."""
    if name == "mixed":
        return f"({layer('roads')} union all {layer('crags')})"
    flag, keep, w, h, shape = RECIPES[name]
    size = f"select *, {w} as w, {h} as h from base where flag = '{flag}' and {keep}"
    shaped = f"select *, {SHAPES[shape]} as shape from ({size})"
    return (
        f"select gid, cast({place_sql(name, 'x')} as int) as x, cast({place_sql(name, 'y')} as int) as y, "
        f"cast(case when shape = 'vline' then 0 else w end as int) as w, cast(case when shape = 'hline' then 0 else h end as int) as h, shape, orderkey, "
        f"shape in ('hline', 'vline', 'hook') as is_line from ({shaped})"
    )


def cells(t: str) -> str:
    """A CTE body: gid, cx, cy, inner_ (1 if interior), d (dimension), for a layer CTE t."""
    return f"""
select gid, cx, cy, cast(count(*) = (case (cx % 2) + (cy % 2) when 2 then 1 when 1 then 2 else 4 end) as int) as inner_, (cx % 2) + (cy % 2) as d from (
  select gid, 2 * i + a as cx, 2 * j + b as cy from (
    select gid, i, j from (select gid, x, y, w, h, shape, unnest(range(x, x + w)) as i from {t} where not is_line), lateral (select unnest(range(y, y + h)) as j)
    where shape = 'rect' or (shape = 'L' and not (i = x + w - 1 and j = y + h - 1)) or (shape = 'ring' and (i in (x, x + w - 1) or j in (y, y + h - 1)))
      or (shape = 'plus' and (i = x + w // 2 or j = y + h // 2))), (values (0), (1), (2)) p(a), (values (0), (1), (2)) q(b)) group by gid, cx, cy
union all
select gid, cx, cy, cast(not ((cx = 2 * x and cy = 2 * y) or (cx = 2 * (x + w) and cy = 2 * (y + h))) as int) as inner_, (cx % 2) + (cy % 2) as d from (
  select gid, x, y, w, h, unnest(range(2 * x, 2 * (x + w) + 1)) as cx, 2 * y as cy from {t} where is_line and w > 0
  union all
  select gid, x, y, w, h, 2 * (x + w) as cx, unnest(range(2 * y + (case when w > 0 then 1 else 0 end), 2 * (y + h) + 1)) as cy from {t} where is_line and h > 0)"""


def candidates(s: str = "s", t: str = "t") -> str:
    return f"select s.gid as sid, t.gid as tid, s.is_line as s_line, t.is_line as t_line from {s} s join {t} t on s.x <= t.x + t.w and t.x <= s.x + s.w and s.y <= t.y + t.h and t.y <= s.y + s.h"


def pair_ctes(name: str) -> str:
    """CTEs up to `matrix`: sid, tid, s_line, t_line, the nine dimensions ii ... ee (-1: empty), for a layer pair."""
    s, t = PAIRS[name] if name in PAIRS else name.split(":")
    return f"""with {BASE}, s as materialized ({layer(s)}), t as materialized ({layer(t)}), c as materialized ({candidates()}),
sc as materialized ({cells('s')}), tc as materialized ({cells('t')}),
sn as (select gid, sum(inner_) as ni, sum(1 - inner_) as nb, max(case when inner_ = 1 then d end) as di from sc group by 1),
tn as (select gid, sum(inner_) as ni, sum(1 - inner_) as nb, max(case when inner_ = 1 then d end) as di from tc group by 1),
shared as (select c.sid, c.tid, max(case when a.inner_ = 1 and b.inner_ = 1 then a.d end) as ii, max(case when a.inner_ = 1 and b.inner_ = 0 then a.d end) as ib,
  max(case when a.inner_ = 0 and b.inner_ = 1 then a.d end) as bi, max(case when a.inner_ = 0 and b.inner_ = 0 then a.d end) as bb,
  sum(a.inner_) as si, sum(1 - a.inner_) as sb, sum(b.inner_) as ti, sum(1 - b.inner_) as tb,
  sum(case when a.inner_ = 1 and a.d = 2 then 1 else 0 end) as si2, sum(case when a.inner_ = 1 and a.d = 1 then 1 else 0 end) as si1, sum(case when a.inner_ = 0 and a.d = 1 then 1 else 0 end) as sb1,
  sum(case when b.inner_ = 1 and b.d = 2 then 1 else 0 end) as ti2, sum(case when b.inner_ = 1 and b.d = 1 then 1 else 0 end) as ti1, sum(case when b.inner_ = 0 and b.d = 1 then 1 else 0 end) as tb1
  from c join sc a on a.gid = c.sid join tc b on b.gid = c.tid and a.cx = b.cx and a.cy = b.cy group by 1, 2),
sd as (select gid, sum(case when inner_ = 1 and d = 2 then 1 else 0 end) as i2, sum(case when inner_ = 1 and d = 1 then 1 else 0 end) as i1, sum(case when inner_ = 0 and d = 1 then 1 else 0 end) as b1 from sc group by 1),
td as (select gid, sum(case when inner_ = 1 and d = 2 then 1 else 0 end) as i2, sum(case when inner_ = 1 and d = 1 then 1 else 0 end) as i1, sum(case when inner_ = 0 and d = 1 then 1 else 0 end) as b1 from tc group by 1),
matrix as materialized (select c.sid, c.tid, c.s_line, c.t_line, coalesce(h.ii, -1) as ii, coalesce(h.ib, -1) as ib, coalesce(h.bi, -1) as bi, coalesce(h.bb, -1) as bb,
  case when coalesce(h.si2, 0) < sd.i2 then 2 when coalesce(h.si1, 0) < sd.i1 then 1 when coalesce(h.si, 0) < sn.ni then 0 else -1 end as ie,
  case when coalesce(h.sb1, 0) < sd.b1 then 1 when coalesce(h.sb, 0) < sn.nb then 0 else -1 end as be,
  case when coalesce(h.ti2, 0) < td.i2 then 2 when coalesce(h.ti1, 0) < td.i1 then 1 when coalesce(h.ti, 0) < tn.ni then 0 else -1 end as ei,
  case when coalesce(h.tb1, 0) < td.b1 then 1 when coalesce(h.tb, 0) < tn.nb then 0 else -1 end as eb
  from c left join shared h using (sid, tid) join sn on sn.gid = c.sid join tn on tn.gid = c.tid join sd on sd.gid = c.sid join td on td.gid = c.tid),
flags as (select *, (ii >= 0 or ib >= 0 or bi >= 0 or bb >= 0) as intersects,
  (ii < 0 and (ib >= 0 or bi >= 0 or bb >= 0)) as touches, (ii >= 0 and ie < 0 and be < 0) as within, (ii >= 0 and ei < 0 and eb < 0) as contains,
  ((ii >= 0 or ib >= 0 or bi >= 0 or bb >= 0) and ei < 0 and eb < 0) as covers, ((ii >= 0 or ib >= 0 or bi >= 0 or bb >= 0) and ie < 0 and be < 0) as covered_by,
  (ii >= 0 and ie < 0 and be < 0 and ei < 0 and eb < 0) as equals,
  case when s_line and not t_line then ii >= 0 and ie >= 0 when t_line and not s_line then ii >= 0 and ei >= 0 when s_line and t_line then ii = 0 else false end as crosses,
  case when s_line and t_line then ii = 1 and ie >= 0 and ei >= 0 when not s_line and not t_line then ii >= 0 and ie >= 0 and ei >= 0 else false end as "overlaps"
  from matrix)
"""


#: Points of a geometry by its shape.
POINTS = "case shape when 'rect' then 5 when 'L' then 7 when 'ring' then 10 when 'plus' then 13 when 'hook' then 3 else 2 end"
RELATIONS = ("contains", "covered_by", "covers", "crosses", "equals", "intersects", "overlaps", "touches", "within")


def links(name: str, relations: tuple[str, ...] = RELATIONS) -> str:
    parts = " union all ".join(f"select sid, '{r}' as relation, tid from flags where \"{r}\"" for r in relations)
    return f"{pair_ctes(name)} {parts}"


def counts(name: str) -> str:
    parts = " union all ".join(f"select '{r}' as relation, cast(count(*) filter (where \"{r}\") as bigint) as pairs from flags" for r in RELATIONS)
    return f"{pair_ctes(name)} {parts}"


def text(v: str) -> str:
    return f"substr('F012', {v} + 2, 1)"


def matrices(name: str) -> str:
    cols = " || ".join([*(text(c) for c in ("ii", "ib", "ie", "bi", "bb", "be", "ei", "eb")), "'2'"])
    return f"{pair_ctes(name)} select sid, tid, {cols} as matrix from matrix"


def pairs(name: str) -> str:
    """with ... c(sid, tid): MBR theta join only."""
    s, t = PAIRS[name] if name in PAIRS else name.split(":")
    return f"with {BASE}, s as materialized ({layer(s)}), t as materialized ({layer(t)}), c as materialized ({candidates()})"


def tile(*sides: str) -> str:
    both = " union all ".join(f"select w, h from {s}" for s in sides)
    return f"tile as (select avg(cast(w as double)) as tw, avg(cast(h as double)) as th from ({both}))"


def scored(name: str, primary: str = "js", secondary: str | None = None, sides: tuple[str, ...] = ("s",)) -> str:
    """CTEs up to `w`: sid, tid, weight, second, tile ranges and counts, with the mean tile of the sides."""
    e = {"cf": "cast(k as double)", "js": "cast(k as double) / (ks + kt - k)", "mbro": "case when ua > 0 then ia / ua else 0.0 end", "isp": "1.0 / (sp + tp)", "chi2": "case when (k + (ks - k)) * ((kt - k) + (n - ks - kt + k)) * (k + (kt - k)) * ((ks - k) + (n - ks - kt + k)) > 0 then n * pow(cast(k as double) * (n - ks - kt + k) - cast(ks - k as double) * (kt - k), 2) / ((cast(k as double) + (ks - k)) * (cast(kt - k as double) + (n - ks - kt + k)) * (cast(k as double) + (kt - k)) * (cast(ks - k as double) + (n - ks - kt + k))) else 0.0 end"}
    return f"""{pairs(name)}, {tile(*sides)},
r as (select c.sid, c.tid, cast(floor(s.x / tw) as bigint) as sx1, cast(floor((s.x + s.w) / tw) as bigint) as sx2, cast(floor(s.y / th) as bigint) as sy1, cast(floor((s.y + s.h) / th) as bigint) as sy2,
  cast(floor(t.x / tw) as bigint) as tx1, cast(floor((t.x + t.w) / tw) as bigint) as tx2, cast(floor(t.y / th) as bigint) as ty1, cast(floor((t.y + t.h) / th) as bigint) as ty2,
  greatest(0.0, least(s.x + s.w, t.x + t.w) - greatest(s.x, t.x)) * greatest(0.0, least(s.y + s.h, t.y + t.h) - greatest(s.y, t.y)) as ia, cast(s.w * s.h + t.w * t.h as double) as ab,
  s.np as sp, t.np as tp from c join (select *, {POINTS} as np from s) s on s.gid = c.sid join (select *, {POINTS} as np from t) t on t.gid = c.tid, tile),
ext as (select (select (floor(max(x + w) / any_value(tw)) - floor(min(x) / any_value(tw)) + 1) * (floor(max(y + h) / any_value(th)) - floor(min(y) / any_value(th)) + 1) from (select x, y, w, h from s union all select x, y, w, h from t), tile) as n),
q as (select r.*, (least(sx2, tx2) - greatest(sx1, tx1) + 1) * (least(sy2, ty2) - greatest(sy1, ty1) + 1) as k, (sx2 - sx1 + 1) * (sy2 - sy1 + 1) as ks, (tx2 - tx1 + 1) * (ty2 - ty1 + 1) as kt, ab - ia as ua,
  greatest(sx1, tx1) as tx, least(sy2, ty2) as ty, ext.n as n from r, ext),
w as materialized (select sid, tid, {e[primary]} as weight, {e[secondary] if secondary else '0.0'} as second, tx, ty, k, ks, kt from q)"""
