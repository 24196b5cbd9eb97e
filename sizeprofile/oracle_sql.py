"""Independent SQL of the exact queries, for an engine that reads the same tables.

Estimators appear in forms unlike those of the package: isotonic fits as the min-max of interval means or lower
medians, or (sorted sizes) threshold by threshold with running minima of prefix sums; matching as a join of single groups on
their ranks, or as overlapping rank intervals with shares by recursion.
"""

from __future__ import annotations

from .sources.workloads import WORKLOADS

RUNS = ((0, "s0"), (1, "s1"))

#: Workload texts that the two engines spell differently: (groups, entities).
SPELT = {
    "w16": ("select doc_id as group_id, lang, source from documents", r"select doc_id as group_id from (select doc_id, unnest(string_split(trim(regexp_replace(text, '[ \t\n\r]+', ' ', 'g')), ' ')) as w from documents) t where w <> ''"),
    "w17": ("select user_id || ':' || cast(cast(ts as date) as varchar) as group_id, strftime(date_trunc('week', ts), '%Y-%m-%d') as week, cast(cast(ts as date) as varchar) as day from events group by user_id, cast(ts as date), date_trunc('week', ts)", "select user_id || ':' || cast(cast(ts as date) as varchar) as group_id from events"),
    "w21b": ("select distinct split_part(regexp_replace(url, '^[a-z]+://', ''), '/', 1) as group_id from pages", "select split_part(regexp_replace(url, '^[a-z]+://', ''), '/', 1) as group_id from pages"),
}


def base(w: str, ceiling: int | None = None) -> str:
    """CTEs g (group_id, leaf_id, l0..), sizes, counts (level, node_id, g), hist (level, node_id, size, cnt), nodes."""
    x = WORKLOADS[w]
    k = x.ceiling if ceiling is None else ceiling
    groups, entities = SPELT.get(w, (x.groups, x.entities))
    paths = ["'all'", *[f"concat_ws('/', {', '.join(f'{c}::varchar' for c in x.levels[: j + 1])})" for j in range(len(x.levels))]]
    cols = ", ".join(f"{p} as l{j}" for j, p in enumerate(paths))
    union = lambda body: " union all ".join(body(j) for j in range(len(paths)))
    return f"""g as (select group_id, {paths[-1]} as leaf_id, {cols} from ({groups}) t),
sizes as (select g.*, least(coalesce(n, 0), {k})::bigint as size from g left join (select group_id, count(*) as n from ({entities}) e group by 1) c on g.group_id = c.group_id),
counts as ({union(lambda j: f"select {j} as level, l{j} as node_id, count(*)::bigint as g from g group by 2")}),
hist as ({union(lambda j: f"select {j} as level, l{j} as node_id, size, count(*)::bigint as cnt from sizes group by 2, 3")}),
nodes as ({union(lambda j: f"select distinct {j} as level, l{j} as node_id, {f'l{j - 1}' if j else 'null'} as parent_id from g")})"""


def runs(eps: str) -> str:
    return f"runs as (select * from (values {', '.join(f'({i}, {s!r}, {eps}::double)' for i, s in RUNS)}) t(run_id, seed, eps))"


def uniform(key: str) -> str:
    return f"((('0x' || substr(md5(concat_ws('|', {key})), 1, 13))::bigint + 0.5) / 4503599627370496.0)"


def geometric(scale: str, key: str) -> str:
    one = lambda c: f"""floor(ln({uniform(f"{key}, '{c}'")}) / (-1.0 / ({scale})))"""
    return f"({one('a')} - {one('b')})::bigint"


def laplace(scale: str, key: str) -> str:
    u = uniform(f"{key}, 'l'")
    return f"(-sign({u} - 0.5) * ({scale}) * ln(1.0 - 2.0 * abs({u} - 0.5)))"


def cumulative(k: int) -> str:
    return f"""cum as (select c.level, c.node_id, c.g, s.size, coalesce(sum(h.cnt), 0)::bigint as cum
  from counts c cross join (select unnest(range({k + 1}))::bigint as size) s left join hist h on h.level = c.level and h.node_id = c.node_id and h.size <= s.size group by all)"""


def hc_cells(k: int) -> str:
    return cumulative(k) + f""",
cells as (select run_id, level, node_id, size, g, cum + {geometric('1.0 / eps', 'seed, level, node_id, size')} as noisy from cum, runs where size < {k})"""


def minmax(cells: str, place: str, p: int, out: str) -> str:
    """Fit of `cells` (run_id, level, node_id, <place>, noisy) as CTE `out` with column fit."""
    value = "avg(b.noisy)" if p == 2 else "quantile_disc(b.noisy, 0.5)"
    return f"""ends_{out} as (select a.run_id, a.level, a.node_id, a.{place} as l, c.{place} as r, {value} as v from {cells} a join {cells} c on a.run_id = c.run_id and a.level = c.level and a.node_id = c.node_id and c.{place} >= a.{place}
  join {cells} b on a.run_id = b.run_id and a.level = b.level and a.node_id = b.node_id and b.{place} between a.{place} and c.{place} group by all),
low_{out} as (select e.run_id, e.level, e.node_id, e.l, i.{place} as i, min(e.v) as v from ends_{out} e join {cells} i on i.run_id = e.run_id and i.level = e.level and i.node_id = e.node_id and i.{place} between e.l and e.r group by all),
{out} as (select run_id, level, node_id, i, max(v)::double as fit from low_{out} group by all)"""


def hc_release(k: int, p: int = 1, out: str = "est") -> str:
    return hc_cells(k) + ",\n" + minmax("cells", "size", p, "hcfit") + f""",
hcint as (select f.run_id, f.level, f.node_id, f.i as size, floor(least(greatest(f.fit, 0.0), c.g::double) + 0.5)::bigint as cum from hcfit f join counts c on c.level = f.level and c.node_id = f.node_id
  union all select run_id, level, node_id, {k}, g from counts, runs),
{out} as (select * from (select run_id, level, node_id, size::bigint as size, (cum - lag(cum, 1, 0) over (partition by run_id, level, node_id order by size))::bigint as cnt from hcint) t where cnt <> 0)"""


def hg_cells() -> str:
    return f"""hgraw as (select level, node_id, size, unnest(range(1, cnt + 1)) as j from hist),
hgnum as (select *, row_number() over (partition by level, node_id order by size, j) as i from hgraw),
hgcells as (select run_id, level, node_id, size, j, i, size + {geometric('1.0 / eps', 'seed, level, node_id, size, j')} as noisy from hgnum, runs)"""


def hg_release(p: int = 2, out: str = "est") -> str:
    """Released sizes of the sorted-size method: how many whole sizes k a fit reaches after rounding.

    A fit at rank i reaches a bar if for some left end all intervals up to right ends at i or beyond do: for squares their
    mean reaches k - 1/2, for absolute gaps more than half of their values are above k - 1. Either is a sign of sums
    of one number a value, so of prefix sums: the least from i on against the least before i.
    """
    d, meets = ("2 * noisy - 2 * k + 1", ">=") if p == 2 else ("case when noisy > k - 1 then 1 else -1 end", ">")
    return hg_cells() + f""",
bars as (select run_id, level, node_id, unnest(range(1, greatest(top, 0) + 1)) as k from (select run_id, level, node_id, max(noisy) as top from hgcells group by all) t),
prefix as (select run_id, level, node_id, k, i, sum({d}) over (partition by run_id, level, node_id, k order by i rows unbounded preceding) as s from hgcells join bars using (run_id, level, node_id)),
ahead as (select run_id, level, node_id, k, i, min(s) over (partition by run_id, level, node_id, k order by i rows between current row and unbounded following) as hi, least(0, coalesce(min(s) over (partition by run_id, level, node_id, k order by i rows between unbounded preceding and 1 preceding), 0)) as lo from prefix),
reached as (select run_id, level, node_id, i, count(*) filter (where hi {meets} lo) as size from ahead group by all),
{out} as (select run_id, level, node_id, coalesce(r.size, 0)::bigint as size, count(*)::bigint as cnt from hgcells left join reached r using (run_id, level, node_id, i) group by all)"""


def with_variance(est: str, method: str, out: str = "vest") -> str:
    unit = "2.0 / (eps * eps)"
    return f"{out} as (select e.run_id, e.level, e.node_id, e.size, e.cnt, {'2.0 * (' + unit + ')' if method == 'hc' else '(' + unit + ')'} / e.cnt as var from {est} e join runs using (run_id))"


def hamilton(levels: int, est: str = "vest", first: str = "level = 0", how: str = "weighted") -> str:
    """CTEs seg1, match1 .. and `rel`: estimates with variances made consistent, with largest-remainder shares by recursion."""
    one = "(1.0 / p_var + 1.0 / c_var)"
    size, var = (f"floor((p_new / p_var + c_size / c_var) / {one} + 0.5)::bigint", f"1.0 / {one}") if how == "weighted" else ("floor((p_new::double + c_size) / 2.0 + 0.5)::bigint", "(p_var + c_var) / 4.0")
    sql = f"now0 as (select run_id, node_id, size as old, size as new, var, cnt from {est} where {first})"
    for k in range(1, levels):
        key = "run_id, parent_id, c_size"
        sql += f""",
top{k} as (select run_id, node_id as parent_id, old as p_size, new as p_new, var as p_var, cnt, sum(cnt) over (partition by run_id, node_id order by old, new, var rows unbounded preceding) as hi from now{k - 1}),
kid{k} as (select e.run_id, n.parent_id, e.node_id as child_id, e.size as c_size, e.var as c_var, e.cnt from {est} e join nodes n on n.level = e.level and n.node_id = e.node_id where e.level = {k}),
pool{k} as (select *, sum(cnt) over (partition by run_id, parent_id order by c_size rows unbounded preceding) as hi from (select {key}, sum(cnt) as cnt from kid{k} group by all) t),
seg{k} as (select p.run_id, p.parent_id, p.p_size, p.p_new, p.p_var, c.c_size, (least(p.hi, c.hi) - greatest(p.hi - p.cnt, c.hi - c.cnt))::bigint as n, row_number() over (partition by p.run_id, p.parent_id, c.c_size order by p.hi) as k
  from top{k} p join pool{k} c on c.run_id = p.run_id and c.parent_id = p.parent_id and c.hi - c.cnt < p.hi and p.hi - p.cnt < c.hi),
held{k} as (select {key}, list(child_id order by child_id) as ids, list(c_var order by child_id) as vars, list(cnt::bigint order by child_id) as amounts from kid{k} group by {key}),
deal{k}(run_id, parent_id, c_size, k, amounts, share) as (
  select {key}, 0::bigint, amounts, amounts from held{k}
  union all
  select {key}, k, list_transform(range(1, len(share) + 1), lambda i: amounts[i] - share[i]), share from (
    select *, list_transform(range(1, len(low) + 1), lambda i: low[i] + case when place[i] < short then 1 else 0 end) as share from (
      select *, n - list_sum(low)::bigint as short, list_transform(range(1, len(low) + 1), lambda i: len(list_filter(range(1, len(low) + 1), lambda j: part[j] > part[i] or (part[j] = part[i] and j < i)))) as place from (
        select {', '.join('d.' + c for c in key.split(', '))}, s.k, s.n, d.amounts, list_transform(d.amounts, lambda r: s.n * r // list_sum(d.amounts)::bigint) as low, list_transform(d.amounts, lambda r: s.n * r % list_sum(d.amounts)::bigint) as part
        from deal{k} d join seg{k} s on s.run_id = d.run_id and s.parent_id = d.parent_id and s.c_size = d.c_size and s.k = d.k + 1) a) b) c),
match{k} as (select s.run_id, s.parent_id, s.p_size, s.p_new, s.p_var, h.ids[t.i] as child_id, s.c_size, h.vars[t.i] as c_var, d.share[t.i] as n
  from seg{k} s join deal{k} d on d.run_id = s.run_id and d.parent_id = s.parent_id and d.c_size = s.c_size and d.k = s.k
  join held{k} h on h.run_id = s.run_id and h.parent_id = s.parent_id and h.c_size = s.c_size join (select unnest(range(1, 1001)) as i) t on t.i <= len(h.ids) where d.share[t.i] > 0),
now{k} as (select run_id, node_id, old, new, var, sum(n) as cnt from (select run_id, child_id as node_id, c_size as old, {size} as new, {var} as var, n from match{k}) t group by all)"""
    last = levels - 1
    names = ", ".join(f"l{j}" for j in range(levels))
    rel = " union all ".join(f"select run_id, {j} as level, l{j} as node_id, new as size, sum(cnt)::bigint as cnt from now{last} m join (select distinct {names} from g) t on t.l{last} = m.node_id group by all" for j in range(levels))
    return sql + f",\nrel as ({rel})"


def topdown(levels: int, how: str) -> str:
    """CTEs m1 .. and `rel`: est (hc) made consistent, spread shares, single groups joined by rank."""
    one = "(1.0 / a.var + 1.0 / b.var)"
    size = f"floor((a.new / a.var + b.size / b.var) / {one} + 0.5)::bigint" if how == "weighted" else "floor((a.new::double + b.size) / 2.0 + 0.5)::bigint"
    var = f"1.0 / {one}" if how == "weighted" else "(a.var + b.var) / 4.0"
    sql = """singles as (select run_id, level, node_id, size, 4.0 / (eps * eps * cnt) as var, cnt, unnest(range(1, cnt + 1)) as j from est join runs using (run_id)),
m0 as (select run_id, node_id, size as old, size as new, 4.0 / (eps * eps * cnt) as var, unnest(range(cnt)) as x from est join runs using (run_id) where level = 0)"""
    for k in range(1, levels):
        sql += f""",
a{k} as (select run_id, node_id as parent_id, old, new, var, row_number() over (partition by run_id, node_id order by old, new, var) as i from m{k - 1}),
b{k} as (select s.run_id, n.parent_id, s.node_id, s.size, s.var, row_number() over (partition by s.run_id, n.parent_id order by s.size, (2 * s.j - 1)::double / (2 * s.cnt), s.node_id) as i from singles s join nodes n on n.level = s.level and n.node_id = s.node_id where s.level = {k}),
m{k} as (select b.run_id, b.node_id, b.size as old, {size} as new, {var} as var, a.parent_id, a.old as p_size, a.new as p_new, a.var as p_var, b.var as c_var from a{k} a join b{k} b on a.run_id = b.run_id and a.parent_id = b.parent_id and a.i = b.i)"""
    last = levels - 1
    names = ", ".join(f"l{j}" for j in range(levels))
    rel = " union all ".join(f"select run_id, {j} as level, l{j} as node_id, new as size, count(*)::bigint as cnt from (select m.run_id, m.new, t.* from m{last} m join (select distinct {names} from g) t on t.l{last} = m.node_id) group by all" for j in range(levels))
    return sql + f",\nrel as ({rel})"


def emd(est: str = "rel", tag: str = "") -> str:
    return f"""truth{tag} as (select run_id, level, node_id, size, cnt from hist, (select run_id from runs)),
gap{tag} as (select run_id, level, node_id, size, sum(d) as d from (select run_id, level, node_id, size, cnt as d from {est} union all select run_id, level, node_id, size, -cnt from truth{tag} where (run_id, level) in (select run_id, level from {est})) t group by all),
step{tag} as (select run_id, level, node_id, abs(sum(d) over (partition by run_id, level, node_id order by size rows unbounded preceding)) as gap, lead(size) over (partition by run_id, level, node_id order by size) - size as width from gap{tag}),
emd{tag} as (select run_id, level, node_id, coalesce(sum(gap * width), 0)::bigint as emd from step{tag} group by all)"""


def error_profile(bucket: int = 100) -> str:
    """CTE `profile` from truth and rel: overlapping rank intervals by the block of their first rank."""
    upto = "sum(cnt) over (partition by run_id, level, node_id order by size rows unbounded preceding)"
    return f"""tru as (select *, {upto} as hi from truth), est2 as (select *, {upto} as hi from rel),
lap as (select a.run_id, a.level, a.node_id, greatest(a.hi - a.cnt, b.hi - b.cnt) as lo, least(a.hi, b.hi) as hi, a.size as p_size, b.size as c_size from tru a join est2 b on a.run_id = b.run_id and a.level = b.level and a.node_id = b.node_id and a.hi - a.cnt < b.hi and b.hi - b.cnt < a.hi),
profile as (select run_id, level, node_id, (lo // {bucket})::bigint as bucket, sum(hi - lo)::bigint as n, sum((hi - lo) * (c_size - p_size))::bigint as error, min(p_size) as min_size, max(p_size) as max_size from lap group by all)"""


def stmt(*ctes: str, body: str) -> str:
    return "with recursive " + ",\n".join(ctes) + "\n" + body
