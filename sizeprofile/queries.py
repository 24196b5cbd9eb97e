"""Every method, variant, baseline, measure and workload as a query (spark, sf_dir) -> DataFrame, with exact SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import oracle_sql as q
from .functions import aggregates
from .functions.isotonic import fit_by_node
from .functions.noise import geometric_noise, laplace_noise
from .operators import estimators as est
from .operators import matching, metrics, profile, release_queries
from .operators.estimators import KEYS
from .operators.tree import RegionTree
from .plans import experiments, release
from .plans.meter import StageMeter
from .sources.workloads import WORKLOADS
from .streaming import sizes as stream

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}
EXACT = ("w1", "w3", "w4", "w5", "w9", "w18", "w20")


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _runs(spark, eps: float) -> DataFrame:
    return est.runs_table(spark, [(i, s, eps) for i, s in q.RUNS])


def _whole(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


# representations

for _w in EXACT:
    @query(f"sizes_{_w}", q.stmt(q.base(_w), body="select group_id, leaf_id, size from sizes"))
    def _(spark, d, w=_w):
        entities, groups, _tree = WORKLOADS[w].load(spark, d)
        return profile.clamp_sizes(profile.group_sizes(entities, groups), WORKLOADS[w].ceiling)

    @query(f"hist_rollup_{_w}", q.stmt(q.base(_w), body="select * from hist"))
    def _(spark, d, w=_w):
        return WORKLOADS[w].histogram(spark, d)[0]

    @query(f"dataset_stats_{_w}", q.stmt(q.base(_w, 1 << 40), body="select sum(cnt)::bigint as n_groups, sum(cnt * size)::bigint as n_entities, count(distinct size) as n_sizes, max(size) as max_size from hist where level = 0"))
    def _(spark, d, w=_w):
        entities, groups, tree = WORKLOADS[w].load(spark, d)
        return profile.dataset_stats(profile.rollup_histogram(profile.leaf_histogram(profile.group_sizes(entities, groups)), tree).where("level = 0"))


for _w in sorted(set(WORKLOADS) - set(EXACT)):
    @query(f"hist_rollup_{_w}", q.stmt(q.base(_w), body="select * from hist"))
    def _(spark, d, w=_w):
        return WORKLOADS[w].histogram(spark, d)[0]


def _hist(spark, d, w="w1"):
    return WORKLOADS[w].histogram(spark, d)


@query("hist_leaf", q.stmt(q.base("w1"), body="select leaf_id, size, count(*) as cnt from sizes group by all"))
def _(spark, d):
    entities, groups, _tree = WORKLOADS["w1"].load(spark, d)
    return profile.leaf_histogram(profile.clamp_sizes(profile.group_sizes(entities, groups), 64))


@query("hist_grouping_sets", q.stmt(q.base("w1"), body="select * from hist"))
def _(spark, d):
    entities, groups, tree = WORKLOADS["w1"].load(spark, d)
    return profile.grouping_sets_histogram(profile.leaf_histogram(profile.group_sizes(entities, groups)), tree)


@query("cum_form", q.stmt(q.base("w1"), q.cumulative(64), body="select level, node_id, size, cum from cum"))
def _(spark, d):
    hist, counts, _ = _hist(spark, d)
    return profile.to_cumulative(hist, counts, 64)


_RUNS_SQL = "select level, node_id, size, cnt, (sum(cnt) over w - cnt)::bigint as rank_lo, (sum(cnt) over w)::bigint as rank_hi from hist window w as (partition by level, node_id order by size rows unbounded preceding)"


@query("runs_form", q.stmt(q.base("w1"), body=_RUNS_SQL))
def _(spark, d):
    return profile.to_runs(_hist(spark, d)[0])


@query("cum_to_runs", q.stmt(q.base("w1"), body=_RUNS_SQL))
def _(spark, d):
    hist, counts, _ = _hist(spark, d)
    return profile.cumulative_to_runs(profile.to_cumulative(hist, counts, 64))


@query("sorted_form", q.stmt(q.base("w5"), body=" union all ".join(f"select {j} as level, l{j} as node_id, (row_number() over (partition by l{j} order by size) - 1)::bigint as idx, size from sizes" for j in range(3))))
def _(spark, d):
    return profile.to_sorted_sizes(_hist(spark, d, "w5")[0])


@query("hist_roundtrip", q.stmt(q.base("w4"), body="select * from hist"))
def _(spark, d):
    hist, counts, _ = _hist(spark, d, "w4")
    there = profile.from_cumulative(profile.to_cumulative(profile.from_sorted_sizes(profile.to_sorted_sizes(hist)), counts, 256))
    return profile.from_array(profile.as_array(there))


@query("hist_array", q.stmt(q.base("w1"), body="select level, node_id, list_aggregate(list_transform(range(max(size) + 1), lambda i: coalesce(list_sum(list_transform(list_filter(list({'s': size, 'c': cnt}), lambda x: x.s = i), lambda x: x.c)), 0)::bigint), 'string_agg', ',') as h from hist group by level, node_id"))
def _(spark, d):
    return profile.as_array(_hist(spark, d)[0]).select("level", "node_id", F.array_join(F.col("h").cast("array<string>"), ",").alias("h"))


@query("hist_map", q.stmt(q.base("w1"), body="select level, node_id, string_agg(size || ':' || cnt, ',' order by size) as h from hist group by level, node_id"))
def _(spark, d):
    return profile.as_map(_hist(spark, d)[0]).select("level", "node_id", F.expr("array_join(transform(map_entries(h), e -> concat(e.key, ':', e.value)), ',')").alias("h"))


@query("array_cumulative", q.stmt(q.base("w1"), body="select level, node_id, size, sum(cnt) over (partition by level, node_id order by size rows unbounded preceding)::bigint as cum from hist"))
def _(spark, d):
    hist = _hist(spark, d)[0]
    cum = profile.array_cumulative(profile.as_array(hist)).select("level", "node_id", F.posexplode("hc").alias("size", "cum"))
    return cum.select("level", "node_id", F.col("size").cast("long").alias("size"), "cum").join(hist.select("level", "node_id", "size"), ["level", "node_id", "size"])


@query("group_counts", q.stmt(q.base("w5"), body="select * from counts"))
def _(spark, d):
    return _hist(spark, d, "w5")[1]


@query("tree_check", "select * from (values ('leaf_paths', 0::bigint), ('node_parents', 0), ('roots', 0), ('group_leaves', 0), ('unknown_leaves', 0), ('group_sums', 0)) t(\"check\", bad)")
def _(spark, d):
    _e, groups, tree = WORKLOADS["w9"].load(spark, d)
    return tree.validate(groups)


_BROKEN = """wide as (select distinct l0, l1, l2, l3 from g),
broken as (select * from wide union all select l0, 'X', l2, l3 from wide where l1 = 'ASIA' union all select 'other', l1, l2, l3 from wide where l1 = 'EUROPE'),
long as (select l3 as leaf_id, unnest([0, 1, 2, 3]) as level, unnest([l0, l1, l2, l3]) as node_id from broken),
nodes2 as (select distinct level, node_id, parent_id from (select unnest([0, 1, 2, 3]) as level, unnest([l0, l1, l2, l3]) as node_id, unnest([null, l0, l1, l2]) as parent_id from broken) t),
grp as (select group_id, leaf_id from g union all select group_id, 'nowhere' from g where group_id % 7 = 0),
leaves as (select leaf_id, count(*) as n from grp group by 1),
tot as (select level, node_id, sum(n) as g from long join leaves using (leaf_id) group by all),
gaps as (select level, node_id, sum(g) as gap from (select t.level - 1 as level, n.parent_id as node_id, t.g from tot t join nodes2 n on n.level = t.level and n.node_id = t.node_id where n.parent_id is not null union all select level, node_id, -g from tot where level < 3) t group by all)"""


@query("tree_check_broken", q.stmt(q.base("w9"), _BROKEN, body="""select 'leaf_paths' as "check", count(*) as bad from (select l3 from broken group by 1 having count(*) > 1)
union all select 'node_parents', count(*) from (select level, node_id from nodes2 group by all having count(*) > 1)
union all select 'roots', (count(distinct node_id) > 1)::bigint from nodes2 where level = 0
union all select 'group_leaves', count(*) from (select group_id from grp group by 1 having count(distinct leaf_id) > 1)
union all select 'unknown_leaves', count(*) from grp where leaf_id not in (select l3 from broken)
union all select 'group_sums', count(*) from gaps where gap <> 0"""))
def _(spark, d):
    """The checks on a tree with a second parent over some leaves, a second root over others, and groups in two leaves."""
    _e, groups, tree = WORKLOADS["w9"].load(spark, d)
    wide = tree.wide.unionByName(tree.wide.where("level_1 = 'ASIA'").withColumn("level_1", F.lit("X"))).unionByName(tree.wide.where("level_1 = 'EUROPE'").withColumn("level_0", F.lit("other")))
    strays = groups.where("group_id % 7 = 0").withColumn("leaf_id", F.lit("nowhere"))
    return RegionTree(wide, 4).validate(groups.unionByName(strays))


@query("tree_nodes", q.stmt(q.base("w9"), body="select * from nodes"))
def _(spark, d):
    return WORKLOADS["w9"].load(spark, d)[2].nodes()


@query("tree_ancestors", q.stmt(q.base("w9"), body="select group_id, leaf_id, l1 as node_id from g"))
def _(spark, d):
    _e, groups, tree = WORKLOADS["w9"].load(spark, d)
    return tree.ancestor(groups, 1).select("group_id", "leaf_id", "node_id")


_THREE = ["AMERICA", "ASIA", "EUROPE"]


@query("restrict_root", q.stmt(q.base("w1"), body="select level, case when level = 0 then 'all' else node_id end as node_id, size, sum(cnt)::bigint as cnt from (select 0 as level, 'all' as node_id, size, cnt from hist where level = 1 and node_id in ('AMERICA', 'ASIA', 'EUROPE') union all select level, node_id, size, cnt from hist where level > 0 and split_part(node_id, '/', 1) in ('AMERICA', 'ASIA', 'EUROPE')) t group by all"))
def _(spark, d):
    entities, groups, tree = WORKLOADS["w1"].load(spark, d)
    tree = tree.restrict(_THREE)
    groups = groups.join(tree.small(tree.wide.select("leaf_id")), "leaf_id", "left_semi")  # before the entities are joined
    return profile.rollup_histogram(profile.leaf_histogram(profile.group_sizes(entities, groups)), tree)


# noise and ceilings

@query("noise_cells", f"select x, {q.geometric('2.0', chr(39) + 'seed' + chr(39) + ', x')} as noise from (select l_orderkey * 8 + l_linenumber as x from lineitem group by 1) t")
def _(spark, d):
    rows = spark.read.parquet(f"{d}/lineitem.parquet").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("x")).distinct()
    return rows.select("x", geometric_noise(2.0, "seed", F.col("x")).alias("noise"))


@query("laplace_cells", f"select o_orderkey as x, round({q.laplace('2.0', chr(39) + 'seed' + chr(39) + ', o_orderkey')}, 6) as noise from orders")
def _(spark, d):
    return spark.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("x"), F.round(laplace_noise(2.0, "seed", F.col("o_orderkey")), 6).alias("noise"))


@query("ceiling_estimate", q.stmt(q.base("w1", 1 << 40), body=f"select ceil(max(size) + {q.laplace('1.0 / 0.0001', chr(39) + 'seed' + chr(39) + ', ' + chr(39) + 'ceiling' + chr(39))} + 5 * 10000 * sqrt(2.0))::bigint as ceiling from sizes"))
def _(spark, d):
    entities, groups, _ = WORKLOADS["w1"].load(spark, d)
    return est.estimate_ceiling(profile.group_sizes(entities, groups), "seed")


# single-node estimators

_NAIVE = """x0 as (select c.level, c.node_id, c.g, s.size, coalesce(h.cnt, 0) as cnt from counts c cross join (select unnest(range(65))::bigint as size) s left join hist h on h.level = c.level and h.node_id = c.node_id and h.size = s.size),
xs as (select run_id, level, node_id, size, g, (cnt + {noise})::double as x from x0, runs)""".replace("{noise}", q.geometric("2.0 / eps", "seed, level, node_id, size"))
_PROJECT = """rk as (select *, row_number() over w as k, sum(x) over (partition by run_id, level, node_id order by x desc, size rows unbounded preceding) as s from xs window w as (partition by run_id, level, node_id order by x desc, size)),
th as (select run_id, level, node_id, arg_max((s - g) / k, k) as theta from rk where x - (s - g) / k > 0 group by all),
pr as (select rk.run_id, rk.level, rk.node_id, rk.size, rk.g, case when g <= 0 then 0.0 else greatest(x - theta, 0.0) end as projected from rk join th using (run_id, level, node_id))"""
_ROUND = """fl as (select *, floor(round(projected, 9)) as low from pr),
rr as (select *, row_number() over (partition by run_id, level, node_id order by round(projected - low, 9) desc, size) as r, g - sum(low) over (partition by run_id, level, node_id) as short from fl),
released as (select run_id, level, node_id, size, (low + case when r <= short then 1 else 0 end)::bigint as cnt from rr)"""


@query("naive_noisy", q.stmt(q.base("w1"), q.runs("1.0"), _NAIVE, body="select run_id, level, node_id, size, g, x from xs"))
def _(spark, d):
    hist, counts, _ = _hist(spark, d)
    return est.naive_cells(hist, counts, _runs(spark, 1.0), 64)


@query("naive_projected", q.stmt(q.base("w1"), q.runs("1.0"), _NAIVE, _PROJECT, body="select run_id, level, node_id, size, round(projected, 6) + 0.0 as projected from pr"))
def _(spark, d):
    hist, counts, _ = _hist(spark, d)
    return est.project_simplex(est.naive_cells(hist, counts, _runs(spark, 1.0), 64)).select(*KEYS, "size", (F.round("projected", 6) + 0.0).alias("projected"))


@query("naive_released", q.stmt(q.base("w1"), q.runs("1.0"), _NAIVE, _PROJECT, _ROUND, body="select * from released where cnt > 0"))
def _(spark, d):
    hist, counts, _ = _hist(spark, d)
    return est.estimate_naive(hist, counts, _runs(spark, 1.0), 64)


_EPS = "0.3333333333333333"
_HC = (q.base("w1", 24), q.runs(_EPS))


def _w1(spark, d, ceiling=24, w="w1"):
    entities, groups, tree = WORKLOADS[w].load(spark, d)
    sizes = profile.clamp_sizes(profile.group_sizes(entities, groups), ceiling)
    return profile.rollup_histogram(profile.leaf_histogram(sizes), tree), profile.public_counts(groups, tree), tree


@query("hc_noisy", q.stmt(*_HC, q.hc_cells(24), body="select run_id, level, node_id, size, g, noisy from cells"))
def _(spark, d):
    hist, counts, _ = _w1(spark, d)
    return est.cumulative_cells(hist, counts, _runs(spark, float(_EPS)), 24)


for _p in (1, 2):
    @query(f"hc_l{_p}_fit", q.stmt(*_HC, q.hc_cells(24), q.minmax("cells", "size", _p, "f"), body="select run_id, level, node_id, i as size, round(fit, 6) as fit from f"))
    def _(spark, d, p=_p):
        hist, counts, _ = _w1(spark, d)
        return _whole(fit_by_node(est.cumulative_cells(hist, counts, _runs(spark, float(_EPS)), 24), [*KEYS], ["size"], "noisy", p))

    @query(f"hc_l{_p}_release", q.stmt(*_HC, q.hc_release(24, _p), body="select * from est"))
    def _(spark, d, p=_p):
        hist, counts, _ = _w1(spark, d)
        return est.estimate_cumulative(hist, counts, _runs(spark, float(_EPS)), 24, p)


_HG = (q.base("w3"), q.runs("0.5"))


@query("hg_noisy", q.stmt(*_HG, q.hg_cells(), body="select run_id, level, node_id, size, j, noisy from hgcells"))
def _(spark, d):
    return est.sorted_cells(_hist(spark, d, "w3")[0], _runs(spark, 0.5)).drop("block")


for _p in (1, 2):
    @query(f"hg_l{_p}_release", q.stmt(*_HG, q.hg_release(_p), body="select * from est"))
    def _(spark, d, p=_p):
        return est.estimate_sorted(_hist(spark, d, "w3")[0], _runs(spark, 0.5), p)


for _p in (1, 2):
    @query(f"hg_l{_p}_by_blocks", q.stmt(*_HG, q.hg_release(_p), body="select * from est"))
    def _(spark, d, p=_p):
        return est.estimate_sorted(_hist(spark, d, "w3")[0], _runs(spark, 0.5), p, block_rows=5)


@query("hg_chunked_release", q.stmt(*_HG, q.hg_release(), body="select * from est"))
def _(spark, d):
    return est.estimate_sorted(_hist(spark, d, "w3")[0], _runs(spark, 0.5), 2, block_rows=7)


@query("variance_hc", q.stmt(*_HC, q.hc_release(24), body="select run_id, level, node_id, size, cnt, round(4.0 / (eps * eps * cnt), 6) as var from est join runs using (run_id)"))
def _(spark, d):
    hist, counts, _ = _w1(spark, d)
    runs = _runs(spark, float(_EPS))
    return _whole(est.variance(est.estimate_cumulative(hist, counts, runs, 24).withColumn("method", F.lit("hc")), runs).drop("method"))


@query("variance_hg", q.stmt(*_HG, q.hg_release(), body="select run_id, level, node_id, size, cnt, round(2.0 / (eps * eps * cnt), 6) as var from est join runs using (run_id)"))
def _(spark, d):
    runs = _runs(spark, 0.5)
    return _whole(est.variance(est.estimate_sorted(_hist(spark, d, "w3")[0], runs).withColumn("method", F.lit("hg")), runs).drop("method"))


# matching, merging, releases

def _two_sides(spark, d):
    hist, counts, tree = _w1(spark, d)
    runs = _runs(spark, float(_EPS))
    e = est.variance(est.estimate_cumulative(hist.where("level < 2"), counts.where("level < 2"), runs, 24).withColumn("method", F.lit("hc")), runs)
    e = release.frozen(e)
    parent = e.where("level = 0").select("run_id", F.col("node_id").alias("parent_id"), F.col("size").alias("p_size"), F.col("size").alias("p_new"), F.col("var").alias("p_var"), "cnt")
    child = e.where("level = 1").select("run_id", F.lit("all").alias("parent_id"), F.col("node_id").alias("child_id"), F.col("size").alias("c_size"), F.col("var").alias("c_var"), "cnt")
    return parent, child


_TWO = (*_HC, q.hc_release(24), q.topdown(2, "weighted"))


@query("match_segments", q.stmt(*_TWO, body="select run_id, parent_id, p_size, old as c_size, count(*) as n from m1 group by all"))
def _(spark, d):
    return matching.segments(*_two_sides(spark, d)).select("run_id", "parent_id", "p_size", "c_size", "n")


@query("match_spread", q.stmt(*_TWO, body="select run_id, parent_id, p_size, node_id as child_id, old as c_size, count(*) as n from m1 group by all"))
def _(spark, d):
    return matching.match_runs(*_two_sides(spark, d), "spread").select("run_id", "parent_id", "p_size", "child_id", "c_size", "n")


@query("match_hamilton", q.stmt(*_HC, q.hc_release(24), q.with_variance("est", "hc"), q.hamilton(2), body="select run_id, parent_id, p_size, p_new, round(p_var, 6) as p_var, child_id, c_size, round(c_var, 6) as c_var, n from match1"))
def _(spark, d):
    return _whole(matching.match_runs(*_two_sides(spark, d), "hamilton"))


@query("match_check", "select * from (values ('parent', 0::bigint), ('child', 0)) t(\"check\", bad)")
def _(spark, d):
    p, c = _two_sides(spark, d)
    return matching.check_matching(release.frozen(matching.match_runs(p, c)), p, c)


@query("match_check_broken", q.stmt(*_TWO, body="select 'parent' as \"check\", count(distinct (run_id, p_size)) as bad from m1 where node_id = 'ASIA' union all select 'child', count(distinct (run_id, old)) from m1 where node_id = 'ASIA'"))
def _(spark, d):
    """The check on a matching that has lost one child."""
    p, c = _two_sides(spark, d)
    return matching.check_matching(release.frozen(matching.match_runs(p, c, "spread").where("child_id <> 'ASIA'")), p, c)


def _supplier_blocks(spark, d):
    """Sizes of fifty suppliers at a time, and the same with noise: (run_id, parent_id, size) twice."""
    sizes = spark.read.parquet(f"{d}/lineitem.parquet").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
    block = sizes.select(F.lit(0).alias("run_id"), F.expr("cast(l_suppkey div 50 as string)").alias("parent_id"), F.col("n").alias("size"), "l_suppkey")
    noisy = block.withColumn("size", F.col("size") + geometric_noise(8.0, "blocks", F.col("l_suppkey")))
    return block.drop("l_suppkey"), noisy.drop("l_suppkey")


_BLOCKS = f"""b as (select l_suppkey // 50 as parent_id, l_suppkey, count(*) as size from lineitem group by l_suppkey),
c as (select parent_id, size, size + {q.geometric('8.0', "'blocks', l_suppkey")} as noisy from b),
r as (select x.parent_id, x.size, y.noisy from (select *, row_number() over (partition by parent_id order by size) as i from c) x join (select *, row_number() over (partition by parent_id order by noisy) as i from c) y using (parent_id, i))"""


@query("match_general", q.stmt(_BLOCKS, body="select 0 as run_id, parent_id::varchar as parent_id, sum(abs(size - noisy))::bigint as cost from r group by all"))
def _(spark, d):
    return matching.match_general(*_supplier_blocks(spark, d))


@query("match_greedy")
def _(spark, d):
    return matching.match_greedy_edges(*_supplier_blocks(spark, d))


@query("match_cost", q.stmt(*_TWO, body="select run_id, parent_id, sum(abs(p_size - old))::bigint as cost from m1 group by all"))
def _(spark, d):
    return matching.matching_cost(matching.match_runs(*_two_sides(spark, d)))


for _how in ("weighted", "average"):
    @query(f"merge_{_how}", q.stmt(*_HC, q.hc_release(24), q.topdown(2, _how), body="select run_id, node_id, old, new, round(var, 6) as var, count(*) as cnt from m1 group by run_id, node_id, old, new, m1.var"))
    def _(spark, d, how=_how):
        return _whole(release.merge(matching.match_runs(*_two_sides(spark, d), "spread"), how))

    @query(f"topdown_3level_spread_{_how}", q.stmt(*_HC, q.hc_release(24), q.topdown(3, _how), body="select * from rel"))
    def _(spark, d, how=_how):
        hist, counts, tree = _w1(spark, d)
        return release.release_topdown(hist, counts, tree, _runs(spark, float(_EPS)), "hc", 24, how, share="spread")


def _cut(tree: RegionTree, level: int) -> RegionTree:
    return RegionTree(tree.wide.select(*[f"level_{k}" for k in range(level + 1)]).distinct().withColumn("leaf_id", F.col(f"level_{level}")), level + 1)


@query("topdown_2level_spread", q.stmt(*_TWO, body="select * from rel"))
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    return release.release_topdown(hist.where("level < 2"), counts.where("level < 2"), _cut(tree, 1), _runs(spark, float(_EPS)), "hc", 24, share="spread")


def _mix(methods: list[str]) -> tuple[str, ...]:
    """CTE vest: each level's estimates by its method, with variances."""
    made = [q.hc_release(24, out="est_hc") + ",\n" + q.with_variance("est_hc", "hc", "v_hc") if m == "hc" else q.hg_release(out="est_hg") + ",\n" + q.with_variance("est_hg", "hg", "v_hg") for m in dict.fromkeys(methods)]
    return (*made, "vest as (" + " union all ".join(f"select * from v_{m} where level = {k}" for k, m in enumerate(methods)) + ")")


for _m in ("hc-hc-hc", "hg-hg-hg", "hg-hc-hc", "hc-hg-hg", "hc-hc-hg"):
    @query(f"topdown_hamilton_{_m.replace('-', '_')}", q.stmt(*_HC, *_mix(_m.split("-")), q.hamilton(3), body="select * from rel"))
    def _(spark, d, m=_m):
        hist, counts, tree = _w1(spark, d)
        return release.release_topdown(hist, counts, tree, _runs(spark, float(_EPS)), m.split("-"), 24)


_OK = "select * from (values ('integral', 0::bigint), ('non_negative', 0), ('group_totals', 0), ('parent_is_sum', 0)) t(\"check\", bad)"
for _w in ("w1", "w3", "w4", "w5", "w20"):
    @query(f"audit_topdown_{_w}", _OK)
    def _(spark, d, w=_w):
        hist, counts, tree = _hist(spark, d, w)
        rel = release.frozen(release.release_topdown(hist, counts, tree, _runs(spark, 0.3), "hc", WORKLOADS[w].ceiling))
        return metrics.audit(rel, counts, tree.nodes())


@query("audit_noisy_cells", q.stmt(q.base("w1"), q.runs("1.0"), _NAIVE, body="""select 'integral' as "check", count(*) as bad from xs where x % 2 <> 0
union all select 'non_negative', count(*) from xs where x < 0
union all select 'group_totals', count(*) from (select 1 from xs group by run_id, level, node_id having abs(sum(x) / 2 - max(g)) > 1e-6)
union all select 'parent_is_sum', count(*) from (select 1 from (select run_id, x.level - 1 as level, n.parent_id as node_id, size, x from xs x join nodes n on n.level = x.level and n.node_id = x.node_id where n.parent_id is not null union all select run_id, level, node_id, size, -x from xs where level < 2) t group by run_id, level, node_id, size having sum(x) <> 0)"""))
def _(spark, d):
    """The audit on what is no release: noisy cells, halved."""
    hist, counts, tree = _hist(spark, d)
    cells = release.frozen(est.naive_cells(hist, counts, _runs(spark, 1.0), 64).select(*KEYS, "size", (F.col("x") / 2).alias("cnt")))
    return metrics.audit(cells, counts, tree.nodes())


@query("audit_topdown_updated", _OK)
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    rel = release.frozen(release.release_topdown(hist, counts, tree, _runs(spark, 0.3), ["hg", "hc", "hc"], 24, match_on="updated", exact_variance=True))
    return metrics.audit(rel, counts, tree.nodes())


@query("audit_topdown_fit_blocks", _OK)
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    rel = release.frozen(release.release_topdown(hist, counts, tree, _runs(spark, 0.3), "hg", 24, block_source="fit"))
    return metrics.audit(rel, counts, tree.nodes())


_BEST = """errs as (select 'hc' as method, * from (select * from emd_hc) a union all select 'hg', * from (select * from emd_hg) b),
best as (select level, arg_min(method, (e, method)) as method from (select method, level, avg(e) as e from (select method, run_id, level, avg(coalesce(emd, 0)) as e from (select m.method, r.run_id, c.level, c.node_id from counts c, runs r, (values ('hc'), ('hg')) m(method)) x left join errs using (method, run_id, level, node_id) group by all) t group by all) t group by level),
vest as (select v.* from v_hc v join best b on b.level = v.level and b.method = 'hc' union all select v.* from v_hg v join best b on b.level = v.level and b.method = 'hg')"""
_BOTH = (q.hc_release(24, out="est_hc"), q.with_variance("est_hc", "hc", "v_hc"), q.hg_release(out="est_hg"), q.with_variance("est_hg", "hg", "v_hg"), q.emd("est_hc", "_hc"), q.emd("est_hg", "_hg"))


@query("topdown_best_methods", q.stmt(*_HC, *_BOTH, _BEST, q.hamilton(3), body="select * from rel"))
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    runs = _runs(spark, float(_EPS))
    return release.release_topdown(hist, counts, tree, runs, release.best_methods(hist, counts, tree, runs, 24), 24)


@query("bottom_up", q.stmt(q.base("w1", 24), q.runs("1.0"), q.hc_release(24), body=" union all ".join(f"select run_id, {j} as level, l{j} as node_id, size, sum(cnt)::bigint as cnt from est join (select distinct l0, l1, l2 from g) t on level = 2 and node_id = l2 group by all" for j in range(3))))
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    return release.release_bottom_up(hist, counts, tree, _runs(spark, 1.0), "hc", 24)


@query("independent_violations", q.stmt(*_HC, q.hc_release(24), body="select run_id, level, count(*) as cells from (select run_id, level, node_id, size, sum(d) as d from (select e.run_id, e.level - 1 as level, n.parent_id as node_id, e.size, e.cnt as d from est e join nodes n on n.level = e.level and n.node_id = e.node_id where e.level > 0 union all select run_id, level, node_id, size, -cnt from est where level < 2) t group by all) where d <> 0 group by all"))
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    e = release.frozen(release.release_independent(hist, counts, tree, _runs(spark, float(_EPS)), "hc", 24))
    up = e.join(tree.small(tree.nodes().where("level > 0")), ["level", "node_id"]).select("run_id", (F.col("level") - 1).alias("level"), F.col("parent_id").alias("node_id"), "size", F.col("cnt").alias("d"))
    gaps = up.unionByName(e.where("level < 2").select("run_id", "level", "node_id", "size", (-F.col("cnt")).alias("d"))).groupBy(*KEYS, "size").agg(F.sum("d").alias("d"))
    return gaps.where("d <> 0").groupBy("run_id", "level").agg(F.count(F.lit(1)).alias("cells"))


_MEAN = """sz as (select distinct run_id, size from est),
y as (select z.run_id, n.level, n.node_id, n.parent_id, z.size, coalesce(e.cnt, 0)::double as y from sz z cross join nodes n left join est e on e.run_id = z.run_id and e.level = n.level and e.node_id = n.node_id and e.size = z.size),
s1 as (select run_id, parent_id as node_id, size, sum(y) as s, count(*)::double as v from y where level = 2 group by all),
z1 as (select y.run_id, y.node_id, y.size, (y + s / v) / (1 + 1 / v) as z, 1 / (1 + 1 / v) as u, s, v from y join s1 using (run_id, node_id, size) where level = 1),
s0 as (select run_id, size, sum(z) as s, sum(u) as v from z1 group by all),
h0 as (select y.run_id, y.size, (y + s / v) / (1 + 1 / v) as h, s, v from y join s0 using (run_id, size) where level = 0),
h1 as (select z1.run_id, z1.node_id, z1.size, z1.z + (h0.h - h0.s) * z1.u / h0.v as h, z1.s, z1.v from z1 join h0 using (run_id, size)),
h2 as (select y.run_id, y.node_id, y.size, y.y + (h1.h - h1.s) / h1.v as h from y join h1 on h1.run_id = y.run_id and h1.node_id = y.parent_id and h1.size = y.size where y.level = 2)"""


@query("mean_consistency", q.stmt(*_HC, q.hc_release(24), _MEAN, body="select run_id, 0 as level, 'all' as node_id, size, round(h, 4) + 0.0 as cnt from h0 union all select run_id, 1, node_id, size, round(h, 4) + 0.0 from h1 union all select run_id, 2, node_id, size, round(h, 4) + 0.0 from h2"))
def _(spark, d):
    hist, counts, tree = _w1(spark, d)
    e = release.frozen(release.release_independent(hist, counts, tree, _runs(spark, float(_EPS)), "hc", 24))
    return release.release_mean_consistency(e, tree).select(*KEYS, "size", (F.round("cnt", 4) + 0.0).alias("cnt"))


@query("private_groups")
def _(spark, d):
    _h, counts, tree = _hist(spark, d)
    return release.private_group_counts(counts, tree, "s0", 1.0)


# measures

@query("omniscient_expected", q.stmt(q.base("w1"), q.runs("0.1"), body="select run_id, level, node_id, round(count(distinct size) * sqrt(2.0) / eps, 6) as emd from hist, runs group by run_id, level, node_id, eps"))
def _(spark, d):
    return _whole(metrics.omniscient_expected(_hist(spark, d)[0], _runs(spark, 0.1)))


@query("omniscient_simulated", q.stmt(q.base("w1"), q.runs("0.1"), body=f"""select run_id, level, node_id, round(sum(abs({q.laplace("1.0 / eps", "seed, level, node_id, size, 'omniscient'")})), 6) as emd from hist, runs group by run_id, level, node_id"""))
def _(spark, d):
    return _whole(metrics.omniscient_simulated(_hist(spark, d)[0], _runs(spark, 0.1)))


def _released(spark, d):
    hist, counts, tree = _w1(spark, d)
    runs = _runs(spark, float(_EPS))
    rel = release.frozen(release.release_topdown(hist, counts, tree, runs, "hc", 24, share="spread"))
    return metrics.for_runs(hist, runs), rel, counts


_REL = (*_HC, q.hc_release(24), q.topdown(3, "weighted"))
_EMD = (*_REL, q.emd())


@query("emd_cumulative", q.stmt(*_EMD, body="select * from emd"))
def _(spark, d):
    return metrics.emd(*_released(spark, d)[:2])


@query("emd_sorted", q.stmt(*_EMD, body="select * from emd"))
def _(spark, d):
    return metrics.emd_sorted(*_released(spark, d)[:2])


@query("l1_l2_distance", q.stmt(*_EMD, body="select run_id, level, node_id, sum(abs(d))::bigint as l1, sum(d * d)::bigint as l2_squared from gap group by all"))
def _(spark, d):
    return metrics.cell_distances(*_released(spark, d)[:2])


_LEVELS = "select run_id, level, avg(coalesce(emd, 0)) as mean_emd, count(*) as nodes from (select c.level, c.node_id, r.run_id from counts c, runs r) x left join emd using (run_id, level, node_id) group by all"


@query("level_report", q.stmt(*_EMD, body=f"select run_id, level, round(mean_emd, 6) as mean_emd, nodes from ({_LEVELS}) t"))
def _(spark, d):
    truth, rel, counts = _released(spark, d)
    return _whole(metrics.level_report(metrics.emd(truth, rel), counts))


@query("run_report", q.stmt(*_EMD, body=f"select level, round(avg(mean_emd), 6) as emd, round(stddev_samp(mean_emd) / sqrt(count(*)), 6) as std_of_mean, count(*) as runs from ({_LEVELS}) t group by level"))
def _(spark, d):
    truth, rel, counts = _released(spark, d)
    return _whole(metrics.run_report(metrics.level_report(metrics.emd(truth, rel), counts)))


@query("compare", q.stmt(*_EMD, body=f"select 'weighted to omniscient' as ratio_of, level, round(a.e / b.e, 6) as ratio from (select level, avg(mean_emd) as e from ({_LEVELS}) t group by 1) a join (select level, avg(e) as e from (select run_id, level, avg(n * sqrt(2.0) / eps) as e from (select level, node_id, count(distinct size) as n from hist group by all) h, runs group by all) t group by 1) b using (level)"))
def _(spark, d):
    """Error of the top-down release against what one would expect who knows the sizes that occur."""
    truth, rel, counts = _released(spark, d)
    runs = _runs(spark, float(_EPS))
    errors = {"weighted": metrics.emd(truth, rel), "omniscient": metrics.omniscient_expected(_w1(spark, d)[0], runs)}
    reports = [metrics.run_report(metrics.level_report(e, counts)).withColumn("method", F.lit(m)) for m, e in errors.items()]
    return _whole(metrics.compare(reports[0].unionByName(reports[1]), "weighted", "omniscient").select(F.lit("weighted to omniscient").alias("ratio_of"), "level", "ratio"))


@query("emd_aggregate", q.stmt(*_EMD, body="select * from emd"))
def _(spark, d):
    """The distance by the aggregate function, one call a node."""
    truth, rel, _counts = _released(spark, d)
    both = truth.select(*KEYS, "size", F.col("cnt").alias("t")).join(rel.select(*KEYS, "size", F.col("cnt").alias("e")), [*KEYS, "size"], "full")
    return both.groupBy(*KEYS).agg(aggregates.emd_agg("size", "t", "e").alias("emd"))


@query("lower_median_sizes", q.stmt(q.base("w4"), body="select leaf_id, quantile_disc(size, 0.5)::double as median from sizes group by leaf_id"))
def _(spark, d):
    entities, groups, _tree = WORKLOADS["w4"].load(spark, d)
    sizes = profile.clamp_sizes(profile.group_sizes(entities, groups), WORKLOADS["w4"].ceiling)
    return sizes.groupBy("leaf_id").agg(aggregates.lower_median("size").alias("median"))


@query("error_profile", q.stmt(*_EMD, q.error_profile(), body="select * from profile"))
def _(spark, d):
    return metrics.error_profile(*_released(spark, d)[:2])


@query("noise_density", f"select round(avg((noise <> 0)::int), 6) as nonzero, round(avg((noise > 0)::int), 6) as positive from (select {q.geometric('2.0', chr(39) + 'seed' + chr(39) + ', o_orderkey')} as noise from orders) t")
def _(spark, d):
    """Share of empty cells that noise makes non-zero, and positive; the law gives 2a / (1 + a) and half of it."""
    cells = spark.read.parquet(f"{d}/orders.parquet").select(geometric_noise(2.0, "seed", F.col("o_orderkey")).alias("noise"))
    return cells.agg(F.round(F.avg((F.col("noise") != 0).cast("int")), 6).alias("nonzero"), F.round(F.avg((F.col("noise") > 0).cast("int")), 6).alias("positive"))


@query("cost_by_stage")
def _(spark, d):
    """Tasks, rows and bytes of each stage that the histogram of order sizes takes; seconds and bytes depend on the machine."""
    with StageMeter(spark, "histogram") as meter:
        _hist(spark, d)[0].write.format("noop").mode("overwrite").save()
    return meter.by_stage()


# questions to a release

@query("release_quantiles", q.stmt(*_REL, body="select run_id, level, node_id, min(case when upto >= 0.5 * g then size end) as q50, min(case when upto >= 0.9 * g then size end) as q90 from (select *, sum(cnt) over (partition by run_id, level, node_id order by size rows unbounded preceding) as upto, sum(cnt) over (partition by run_id, level, node_id) as g from rel) t group by all"))
def _(spark, d):
    return release_queries.quantile_sizes(_released(spark, d)[1], [0.5, 0.9], KEYS)


@query("release_summary", q.stmt(*_REL, body="select run_id, level, node_id, sum(cnt)::bigint as n_groups, round(sum(cnt * size) / sum(cnt), 6) as mean_size, round(coalesce(sum(cnt) filter (where size = 1), 0) / sum(cnt), 6) as share_of_ones, round(2 * sum(size * (cnt * below + cnt * (cnt + 1) / 2.0)) / (sum(cnt) * sum(cnt * size)) - (sum(cnt) + 1) / sum(cnt), 6) as gini from (select *, sum(cnt) over (partition by run_id, level, node_id order by size rows unbounded preceding) - cnt as below from rel) t group by all"))
def _(spark, d):
    return release_queries.summary(_released(spark, d)[1], KEYS)


@query("release_topk", q.stmt(*_REL, body="select run_id, level, node_id, size, least(cnt, 5 - (upto - cnt))::bigint as n from (select *, sum(cnt) over (partition by run_id, level, node_id order by size desc rows unbounded preceding) as upto from rel) t where upto - cnt < 5"))
def _(spark, d):
    return release_queries.largest_groups(_released(spark, d)[1], 5, KEYS)


@query("release_at_least", q.stmt(*_REL, body="select run_id, level, node_id, sum(case when size >= 7 then cnt else 0 end)::bigint as n from rel group by all"))
def _(spark, d):
    return release_queries.groups_at_least(_released(spark, d)[1], 7, KEYS)


# operators around the methods

@query("synthetic_tail")
def _(spark, d):
    return experiments.tail_workload(spark, d)[0]


@query("events_windowed_sizes", "select date_trunc('day', ts) as day, user_id, count(*) as size from events group by all")
def _(spark, d):
    return stream.tumbling_sizes(spark.read.parquet(f"{d}/events.parquet")).select(F.col("window.start").cast("timestamp_ntz").alias("day"), "user_id", "size")


@query("sliding_sizes", "select time_bucket(interval '6 hours', ts) - i * interval 6 hour as window_start, user_id, count(*) as size from events, range(4) t(i) group by all")
def _(spark, d):
    return stream.sliding_sizes(spark.read.parquet(f"{d}/events.parquet")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "user_id", "size")


@query("session_sizes", """with o as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 30 minute or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from o)
select user_id, min(ts) as session_start, count(*) as size from s group by user_id, k""")
def _(spark, d):
    return stream.session_sizes(spark.read.parquet(f"{d}/events.parquet")).select("user_id", F.col("session.start").cast("timestamp_ntz").alias("session_start"), "size")


@query("json_filtered_sizes", "select user_id, count(*) filter (where json_extract_string(props, '$.k') is not null) as size from events group by user_id")
def _(spark, d):
    return spark.read.parquet(f"{d}/events.parquet").groupBy("user_id").agg(F.count_if(F.get_json_object("props", "$.k").isNotNull()).alias("size"))


@query("semi_anti_checks", "select 'orders without lines' as \"check\", count(*) as n from orders where o_orderkey not in (select l_orderkey from lineitem) union all select 'lines without orders', count(*) from lineitem where l_orderkey not in (select o_orderkey from orders)")
def _(spark, d):
    orders, lines = spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey"), spark.read.parquet(f"{d}/lineitem.parquet").select("l_orderkey")
    a = orders.join(lines, orders.o_orderkey == lines.l_orderkey, "left_anti").agg(F.count(F.lit(1)).alias("n")).select(F.lit("orders without lines").alias("check"), "n")
    return a.unionByName(lines.join(orders, orders.o_orderkey == lines.l_orderkey, "left_anti").agg(F.count(F.lit(1)).alias("n")).select(F.lit("lines without orders").alias("check"), "n"))


@query("set_ops_checks", q.stmt(q.base("w1"), body="select 'both' as kind, count(*) as n from (select size from hist where node_id = 'ASIA' intersect select size from hist where node_id = 'EUROPE') union all select 'either', count(*) from (select size from hist where node_id = 'ASIA' union select size from hist where node_id = 'EUROPE') union all select 'first only', count(*) from (select size from hist where node_id = 'ASIA' except all select size from hist where node_id = 'EUROPE')"))
def _(spark, d):
    hist = _hist(spark, d)[0]
    a, b = (hist.where(F.col("node_id") == n).select("size") for n in ("ASIA", "EUROPE"))
    out = None
    for kind, df in (("both", a.intersect(b)), ("either", a.union(b).distinct()), ("first only", a.exceptAll(b))):
        row = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query("pivot_report", q.stmt(q.base("w1"), body="select size, coalesce(sum(cnt) filter (where node_id = 'ASIA'), 0)::bigint as asia, coalesce(sum(cnt) filter (where node_id = 'EUROPE'), 0)::bigint as europe from hist where level = 1 group by size"))
def _(spark, d):
    wide = _hist(spark, d)[0].where("level = 1").groupBy("size").pivot("node_id", ["ASIA", "EUROPE"]).agg(F.sum("cnt"))
    return wide.select("size", F.coalesce("ASIA", F.lit(0)).alias("asia"), F.coalesce("EUROPE", F.lit(0)).alias("europe"))


# experiments

for _name in experiments.EXPERIMENTS:
    @query(f"exp_{_name}")
    def _(spark, d, name=_name):
        return experiments.EXPERIMENTS[name](spark, d)


def flagship(spark, sf_dir: str) -> DataFrame:
    """The top-down release of order sizes over region and nation, with its error by level."""
    hist, counts, tree = WORKLOADS["w1"].histogram(spark, sf_dir)
    runs = _runs(spark, float(_EPS))
    rel = release.release_topdown(hist, counts, tree, runs, "hc", 64)
    return metrics.run_report(metrics.level_report(metrics.emd(metrics.for_runs(hist, runs), rel), counts))


