"""DuckDB twins: rows as bit masks, all patterns up to a length by joins of the literal list, supports by the mask predicate."""

from __future__ import annotations

from ..operators.constraints import Constraint, score_sql
from ..sources.workloads import WORKLOADS, Workload, dialect


def kind(w: Workload) -> str:
    """The type of a mask."""
    return "bigint" if len(w.items) <= 62 else "hugeint"


def rows_cte(w: Workload) -> str:
    t = kind(w)
    mask = " + ".join(f"(case when {dialect(sql, False)} then {1 << k}::{t} else 0::{t} end)" for k, (_, sql) in enumerate(w.items))
    return f"""flagged as (select ({dialect(w.label, False)})::bigint y, ({mask})::{t} m from {dialect(w.source, False)}),
r as (select m, sum(y)::bigint wp, sum(1 - y)::bigint wn from flagged where y is not null group by m),
tot as (select coalesce(sum(wp), 0)::bigint np, coalesce(sum(wn), 0)::bigint nn from r)"""


def literals_cte(w: Workload, negation: bool, only=None) -> str:
    n, u = len(w.items), kind(w)
    rows = [(k, 1 << k, 0, name) for k, (name, _) in enumerate(w.items)]
    if negation:
        rows += [(k + n, 0, 1 << k, "!" + name) for k, (name, _) in enumerate(w.items) if only is None or name in only]
    body = ", ".join("({}, {}::{}, {}::{}, '{}')".format(i, p, u, q, u, t.replace("'", "''")) for i, p, q, t in rows)
    return f"lits(id, pm, nm, name) as (values {body})"


def patterns_cte(max_len: int, u: str = "bigint") -> str:
    levels = [f"p0 as (select -1 last, 0::{u} pm, 0::{u} nm, 0 size, '' t)"]
    for k in range(1, max_len + 1):
        text = "b.name" if k == 1 else "a.t || ' & ' || b.name"
        levels.append(f"p{k} as (select b.id last, a.pm | b.pm pm, a.nm | b.nm nm, {k} size, {text} t from p{k - 1} a join lits b on b.id > a.last where ((a.pm | b.pm) & (a.nm | b.nm)) = 0)")
    union = " union all ".join(f"select * from p{k}" for k in range(max_len + 1))
    return ",\n".join([*levels, f"pats as ({union})"])


SUPPORTS = "sup as (select p.t, p.size, p.pm, p.nm, sum(r.wp)::bigint x, sum(r.wn)::bigint y from pats p join r on (r.m & p.pm) = p.pm and (r.m & p.nm) = 0 group by all)"
MINIMAL = "where not exists (select 1 from sat t where t.size < s.size and (t.pm & s.pm) = t.pm and (t.nm & s.nm) = t.nm)"
MAXIMAL = "where not exists (select 1 from sat t where t.size > s.size and (t.pm & s.pm) = s.pm and (t.nm & s.nm) = s.nm)"


def supported(workload: str, negation: bool, max_len: int, only=None) -> str:
    w = WORKLOADS[workload]
    return f"with {rows_cte(w)},\n{literals_cte(w, negation, only)},\n{patterns_cte(max_len, kind(w))},\n{SUPPORTS}"


def frequent(workload: str, negation: bool, min_pos: int, only=None, max_len: int | None = None) -> str:
    """Patterns of any length with at least so many positive rows (1 or more): a recursion that extends only those."""
    w = WORKLOADS[workload]
    u = kind(w)
    cap = "" if max_len is None else f" and s.size < {max_len}"
    text = "case when s.size = 0 then b.name else s.t || ' & ' || b.name end"
    step = f"select b.id, s.pm | b.pm, s.nm | b.nm, s.size + 1, {text}, sum(r.wp)::bigint, sum(r.wn)::bigint from sup s join lits b on b.id > s.last and ((s.pm | b.pm) & (s.nm | b.nm)) = 0{cap} join r on (r.m & (s.pm | b.pm)) = (s.pm | b.pm) and (r.m & (s.nm | b.nm)) = 0 group by b.id, s.pm | b.pm, s.nm | b.nm, s.size + 1, {text} having sum(r.wp) >= {min_pos}"
    return f"with recursive {rows_cte(w)},\n{literals_cte(w, negation, only)},\nsup(last, pm, nm, size, t, x, y) as (select -1, 0::{u}, 0::{u}, 0, '', np, nn from tot where np >= {min_pos}\nunion all {step})"


def unbounded(workload: str, negation: bool, constraint: Constraint, min_pos: int, keep: str = MINIMAL, columns: str = "s.t pattern_text, s.x sup_pos, s.y sup_neg", only=None, max_len: int | None = None) -> str:
    """Members of any length, by the constraint's own bound on the positive support."""
    return f"{frequent(workload, negation, min_pos, only, max_len)},\nsat as (select s.*, np, nn from sup s, tot where {constraint.sql()})\nselect {columns} from sat s {keep}"


def members(workload: str, negation: bool, constraint: Constraint, max_len: int, keep: str = MINIMAL, columns: str = "s.t pattern_text, s.x sup_pos, s.y sup_neg") -> str:
    return f"{supported(workload, negation, max_len)},\nsat as (select sup.*, np, nn from sup, tot where {constraint.sql()})\nselect {columns} from sat s {keep}"


def scored_pairs(workload: str, score: str) -> str:
    return f"{supported(workload, False, 2)}\nselect t pattern_text, x sup_pos, y sup_neg, round({score_sql(score)}, 6) score from sup, tot where size = 2"


def rows_of(workload: str, select: str) -> str:
    return f"with {rows_cte(WORKLOADS[workload])}\n{select}"


def jep_count(workload: str, min_pos: int) -> str:
    n = len(WORKLOADS[workload].items)
    return rows_of(workload, f"select count(*)::bigint n_jeps from (select p.g from (select range::bigint g from range({1 << n})) p join r on (r.m & p.g) = p.g group by p.g having sum(r.wp) >= {min_pos} and sum(r.wn) = 0)")


def first_cut(features: dict[str, str], label: str, table: str) -> str:
    """The first cut of the description-length discretiser, null where it is not worth its description."""
    share = lambda a, n: f"case when {a} > 0 then -({a} / {n}) * log2({a} / {n}) else 0 end"
    entropy = lambda a, b: f"({share(a, f'({a} + {b})')} + {share(b, f'({a} + {b})')})"
    classes = lambda a, b: f"(({a} > 0)::int + ({b} > 0)::int)"
    cells = " union all ".join(f"select {k} feature, ({sql})::double v, y from rows_" for k, sql in enumerate(features.values()))
    return f"""with rows_ as (select *, {label} y from {table}),
h as (select feature, v, sum(y)::double p, sum(1 - y)::double q from ({cells}) where v is not null and not isnan(v) group by all),
w as (select *, sum(p) over upto lp, sum(q) over upto lq, sum(p) over whole tp, sum(q) over whole tq, lead(v) over upto nxt from h window upto as (partition by feature order by v), whole as (partition by feature)),
e as (select *, tp + tq n, {entropy('tp', 'tq')} ent, {entropy('lp', 'lq')} e1, {entropy('(tp - lp)', '(tq - lq)')} e2, {classes('tp', 'tq')} c, {classes('lp', 'lq')} c1, {classes('(tp - lp)', '(tq - lq)')} c2 from w where nxt is not null and tp > 0 and tq > 0),
s as (select *, ((lp + lq) * e1 + (n - lp - lq) * e2) / n cost from e),
best as (select * from (select *, min(cost) over (partition by feature) least from s) where cost <= least + 1e-12 qualify row_number() over (partition by feature order by v) = 1)
select f.feature::int feature, case when ent - least > (log2(n - 1) + log2(pow(3, c) - 2) - (c * ent - c1 * e1 - c2 * e2)) / n then (v + nxt) / 2 end cut from (select distinct feature from h) f left join best b on b.feature = f.feature"""
