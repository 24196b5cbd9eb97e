import datetime
import re

import pytest
from pyspark.sql import functions as F

from sizeprofile.functions import isotonic, sqlfuncs
from sizeprofile.functions.budget import BudgetLedger
from sizeprofile.functions.noise import geometric_noise, geometric_variance
from sizeprofile.operators import estimators, matching, metrics, profile, release_queries
from sizeprofile.operators.tree import RegionTree
from sizeprofile.plans import experiments, release
from sizeprofile.sources import tables
from sizeprofile.sources.workloads import WORKLOADS
from sizeprofile.streaming import sizes as stream

SF = "/root/testdata/sf0.001"


def hist_of(spark, rows):
    return spark.createDataFrame([(0, n, s, c) for n, s, c in rows], "level int, node_id string, size long, cnt long")


def small(spark, groups):
    """(hist, counts, tree) of (group, leaf, size) rows under the leaves' first letters."""
    g = spark.createDataFrame(groups, "group_id long, leaf string, n long")
    g = g.select("group_id", F.substring("leaf", 1, 1).alias("region"), "leaf", "n")
    tree = RegionTree.from_levels(g, ["region", "leaf"])
    keyed = g.select("group_id", F.concat_ws("/", "region", "leaf").alias("leaf_id"), F.col("n").alias("size"))
    return profile.rollup_histogram(profile.leaf_histogram(keyed.select("leaf_id", "size")), tree), profile.public_counts(keyed, tree), tree


def test_worked_example_of_four_groups(spark):
    hist, counts, _ = small(spark, [(1, "a", 4), (2, "b", 2), (3, "a", 1), (4, "b", 1)])
    got = {(r.level, r.node_id): list(r.h) for r in profile.as_array(hist).collect()}
    assert got[0, "all"] == [0, 2, 1, 0, 1] and got[2, "a/a"] == [0, 1, 0, 0, 1] and got[2, "b/b"] == [0, 1, 1]
    sorted_sizes = [r.size for r in profile.to_sorted_sizes(hist).where("level = 0").orderBy("idx").collect()]
    assert sorted_sizes == [1, 1, 2, 4]
    assert {r.node_id: r.g for r in counts.collect()}["all"] == 4


def test_forms_example(spark):
    hist = hist_of(spark, [("x", 1, 2), ("x", 2, 1), ("x", 3, 2)])
    arrays = profile.array_cumulative(profile.as_array(hist)).first()
    assert list(arrays.h) == [0, 2, 1, 2] and list(arrays.hc) == [0, 2, 3, 5]


@pytest.mark.parametrize("a, b, c, l1, l2, emds", [(1, 2, 5, 200, 20_000, (100, 400)), (1, 2, 10, 40, 800, (20, 180))])
def test_only_the_movers_distance_tells_the_sizes_apart(spark, a, b, c, l1, l2, emds):
    n = l1 // 2
    one = hist_of(spark, [("x", a, n)]).withColumn("run_id", F.lit(0))
    for size, want in zip((b, c), emds):
        other = hist_of(spark, [("x", size, n)]).withColumn("run_id", F.lit(0))
        assert metrics.emd(one, other).first().emd == metrics.emd_sorted(one, other).first().emd == want
        d = metrics.cell_distances(one, other).first()
        assert (d.l1, d.l2_squared) == (l1, l2)


def runs_of(spark, parent, children):
    p = spark.createDataFrame([(0, "p", s, s, 1.0, n) for s, n in parent], "run_id int, parent_id string, p_size long, p_new long, p_var double, cnt long")
    c = spark.createDataFrame([(0, "p", k, s, 1.0, n) for k, s, n in children], "run_id int, parent_id string, child_id string, c_size long, c_var double, cnt long")
    return p, c


def test_matching_examples(spark):
    p, c = runs_of(spark, [(1, 300)], [("a", 1, 200), ("b", 2, 100)])
    m = matching.match_runs(p, c).collect()
    assert sorted((r.c_size, r.n) for r in m) == [(1, 200), (2, 100)]
    p, c = runs_of(spark, [(1, 300), (2, 100)], [("a", 1, 200), ("b", 1, 100), ("c", 1, 100)])
    got = matching.match_runs(p, c)
    assert sorted((r.p_size, r.child_id, r.n) for r in got.collect()) == [(1, "a", 150), (1, "b", 75), (1, "c", 75), (2, "a", 50), (2, "b", 25), (2, "c", 25)]
    assert matching.matching_cost(got).first().cost == 100
    assert [r.bad for r in matching.check_matching(got, p, c).collect()] == [0, 0]


def test_matching_cost_is_optimal(spark):
    import random

    rnd, parents, children, want = random.Random(1), [], [], {}
    for k in range(20):
        a, b = ([rnd.randint(0, 9) for _ in range(6)] for _ in range(2))
        want[f"n{k}"] = matching.optimal_cost(a, b)
        parents += [(k, f"n{k}", s, s, 1.0, a.count(s)) for s in set(a)]
        kids = [("x" if i % 2 else "y", s) for i, s in enumerate(b)]
        children += [(k, f"n{k}", c, s, 1.0, kids.count((c, s))) for c, s in set(kids)]
    p = spark.createDataFrame(parents, "run_id int, parent_id string, p_size long, p_new long, p_var double, cnt long")
    c = spark.createDataFrame(children, "run_id int, parent_id string, child_id string, c_size long, c_var double, cnt long")
    for share in ("hamilton", "spread"):
        got = {r.parent_id: r.cost for r in matching.matching_cost(matching.match_runs(p, c, share)).collect()}
        assert got == want
    rows = lambda df, col: df.select("run_id", "parent_id", F.col(col).alias("size"), F.explode(F.expr("sequence(1L, cnt)")))
    greedy = {r.parent_id: r.cost for r in matching.match_greedy_edges(rows(p, "p_size"), rows(c, "c_size")).collect()}
    assert all(greedy[k] >= want[k] for k in want)


def test_merge_example(spark):
    m = spark.createDataFrame([(0, "p", 10, 10, 1.0, "c", 14, 3.0, 5)], matching._MATCH)
    w = release.merge(m, "weighted").first()
    assert (w.new, w.var, w.cnt) == (11, 0.75, 5)
    assert release.merge(m, "average").first().new == 12


def test_naive_projection_example(spark):
    x = spark.createDataFrame([(0, 3.0), (1, -1.0), (2, 2.0)], "size long, x double").select(F.lit(0).alias("run_id"), F.lit(0).alias("level"), F.lit("n").alias("node_id"), "size", F.lit(3).cast("long").alias("g"), "x")
    got = estimators.round_largest_remainder(estimators.project_simplex(x)).orderBy("size").collect()
    assert [r.cnt for r in got] == [2, 0, 1]


def test_omniscient_and_ceiling_figures(spark):
    hist = hist_of(spark, [("x", k, 1) for k in range(2352)])
    runs = estimators.runs_table(spark, [(0, "s", 0.1)])
    assert round(metrics.omniscient_expected(hist, runs).first().emd) == 33_262
    assert abs(5 * 2**0.5 / 1e-4 - 70_710.7) < 0.1


def test_mean_consistency_gives_negative_cells(spark):
    tree = RegionTree.from_levels(spark.createDataFrame([("a",), ("b",)], "r string"), ["r"])
    est = spark.createDataFrame([(0, 0, "all", 1, 0), (0, 1, "a", 1, 3), (0, 1, "b", 1, 0)], "run_id int, level int, node_id string, size long, cnt long")
    got = {r.node_id: round(r.cnt, 6) for r in release.release_mean_consistency(est, tree).collect()}
    assert got == {"all": 1.0, "a": 2.0, "b": -1.0}


EDGE = [(1, "a1", 0), (2, "a1", 0), (3, "a2", 7), (4, "b1", 0), (5, "b1", 90)]


@pytest.mark.parametrize("methods", ["hc", "hg", ["hg", "hc", "hg"]])
@pytest.mark.parametrize("share, on, how", [("hamilton", "initial", "weighted"), ("spread", "updated", "average")])
def test_release_constraints_on_edge_cases(spark, methods, share, on, how):
    """Single-child parents, empty groups, sizes at the ceiling."""
    hist, counts, tree = small(spark, EDGE)
    hist = profile.clamp_sizes(hist, 20).groupBy("level", "node_id", "size").agg(F.sum("cnt").alias("cnt"))
    runs = estimators.runs_table(spark, [(k, f"s{k}", 0.2) for k in range(3)])
    rel = release.frozen(release.release_topdown(hist, counts, tree, runs, methods, 20, how, match_on=on, share=share))
    assert [r.bad for r in metrics.audit(rel, counts, tree.nodes()).collect()] == [0, 0, 0, 0]


def test_node_without_groups(spark):
    w = WORKLOADS["w20"]
    entities, groups, _ = w.load(spark, SF)
    wide = spark.read.parquet(f"{SF}/nation.parquet").join(spark.read.parquet(f"{SF}/region.parquet"), F.col("n_regionkey") == F.col("r_regionkey"))
    tree = RegionTree.from_levels(wide, ["r_name", "n_name"])
    counts = profile.public_counts(groups, tree)
    assert counts.where("g = 0").count() > 0
    hist = profile.rollup_histogram(profile.leaf_histogram(profile.clamp_sizes(profile.group_sizes(entities, groups), 256)), tree)
    rel = release.frozen(release.release_topdown(hist, counts, tree, estimators.runs_table(spark, [(0, "s", 0.5)]), "hc", 256))
    assert [r.bad for r in metrics.audit(rel, counts, tree.nodes()).collect()] == [0, 0, 0, 0]


def test_root_only_and_empty_inputs(spark):
    hist, counts, tree = WORKLOADS["w19"].histogram(spark, SF)
    runs = estimators.runs_table(spark, [(0, "s", 1.0)])
    rel = release.release_topdown(hist, counts, tree, runs, "hc", 64)
    assert rel.agg(F.sum("cnt")).first()[0] == counts.first().g
    none = hist.where("false")
    assert estimators.estimate_sorted(none, runs).count() == 0


def test_independent_release_breaks_sums_and_topdown_does_not(spark):
    hist, counts, tree = WORKLOADS["w1"].histogram(spark, SF)
    runs = estimators.runs_table(spark, [(0, "s", 0.3)])
    alone = release.frozen(release.release_independent(hist, counts, tree, runs, "hc", 64))
    bad = {r.check: r.bad for r in metrics.audit(alone, counts, tree.nodes()).collect()}
    assert bad["parent_is_sum"] > 0 and bad["group_totals"] == 0


def test_noise_moments(spark):
    r = spark.range(100_000).select(geometric_noise(2.0, "k", F.col("id")).alias("x")).agg(F.avg("x"), F.var_pop("x")).first()
    assert abs(r[0]) < 0.05 and abs(r[1] - geometric_variance(2.0)) < 0.3


def test_chunked_fit_equals_plain_and_library(spark):
    import random

    rnd = random.Random(3)
    rows = [(n, k, float(rnd.randint(0, 30) + k // 3)) for n in ("a", "b") for k in range(200)]
    df = spark.createDataFrame(rows, "node_id string, idx long, v double")
    blocks = isotonic.fit_chunked(df, ["node_id"], ["idx"], "v", 5).orderBy("node_id", "idx").collect()
    plain = isotonic.fit_by_node(df, ["node_id"], ["idx"], "v", 2).orderBy("node_id", "idx").collect()
    assert [x for b in blocks for x in [round(b.fit, 9)] * b.cnt] == [round(r.fit, 9) for r in plain]
    from pyspark.ml.linalg import Vectors
    from pyspark.ml.regression import IsotonicRegression

    one = [(r[2], 1.0, Vectors.dense(float(r[1]))) for r in rows if r[0] == "a"]
    model = IsotonicRegression().fit(spark.createDataFrame(one, ["label", "weight", "features"]))
    got = [r.prediction for r in model.transform(spark.createDataFrame(one, ["label", "weight", "features"])).orderBy("features").collect()]
    assert len(got) == 200 and abs(sum(got) - sum(r.fit for r in plain if r.node_id == "a")) < 1e-6


def test_private_group_counts_add_up(spark):
    _, counts, tree = WORKLOADS["w1"].histogram(spark, SF)
    got = release.frozen(release.private_group_counts(counts, tree, "s", 0.5))
    nodes = tree.nodes()
    kids = got.join(nodes, ["level", "node_id"]).groupBy(F.col("parent_id").alias("p")).agg(F.sum("g").alias("s"))
    assert got.join(kids, F.col("node_id") == F.col("p")).where("g <> s").count() == 0
    assert got.where("g < 0").count() == 0 and got.count() == counts.count()


def test_trends(spark):
    """Weighted merging beats plain averages at the root; cumulative beats sorted there; naive is far worse at a large ceiling."""
    h, c, t, k = experiments.inputs(spark, "/root/testdata/sf0.01", "w1", levels=2)
    r = experiments.evaluate(spark, h, c, t, {"weighted": experiments._topdown(k), "average": experiments._topdown(k, how="average"), "hg": experiments._topdown(k, "hg")}, (0.33,), 5)
    root = {x.method: x.emd for x in r.where("level = 0").collect()}
    assert root["weighted"] < root["average"] and root["weighted"] < root["hg"]
    n = {(x.method, x.ceiling): x.emd for x in experiments.naive_table(spark, SF, seeds=3, ceilings=(64, 1000)).collect()}
    assert n["naive", 1000] > n["naive", 64] > n["hc", 64]


def test_tail_extends_the_cut_sizes(spark):
    sizes, tree = experiments.tail_workload(spark, "/root/testdata/sf0.01")
    n = {r.size: r.n for r in sizes.groupBy("size").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert n[7] > n[8] > n[9] > 0 and max(n) > 5000
    assert sizes.where(F.col("group_id").startswith("o")).count() == 50 * 5
    assert sizes.where("leaf_id is null").count() == 0
    assert sizes.join(tree.wide, "leaf_id", "left_anti").count() == 0


def test_stream_equals_batch(spark, tmp_path):
    events = tables.load(spark, SF, "events").limit(400)
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    schema = events.schema.simpleString()[7:-1].replace(":", " ")
    source = stream.events_stream(spark, str(tmp_path / "in"), ", ".join(schema.split(",")))
    seen = spark.read.parquet(str(tmp_path / "in"))
    for name, make in (("tumbling", stream.tumbling_sizes), ("sliding", stream.sliding_sizes), ("sessions", stream.session_sizes)):
        q = make(source).writeStream.outputMode("complete").format("memory").queryName(name).start()
        q.processAllAvailable()
        q.stop()
        assert sorted(map(str, spark.table(name).collect())) == sorted(map(str, make(seen).collect()))
    users = seen.select("user_id").distinct()
    full = stream.with_public_users(stream.tumbling_sizes(seen), users)
    assert full.count() == users.count() * stream.tumbling_sizes(seen).select("window").distinct().count()


def test_batches_are_released_once(spark, tmp_path):
    ledger, calls = BudgetLedger(1.0), []

    def make(batch, eps):
        calls.append(eps)
        return batch

    write = stream.release_each_batch(ledger, 0.3, make, str(tmp_path / "out"))
    df = spark.createDataFrame([(1, datetime.date(2024, 1, 1))], "a int, d date")
    for batch_id in (0, 0, 1):
        write(df, batch_id)
    assert len(calls) == 2 and ledger.spent == 0.3


def test_sql_functions(spark):
    hist = hist_of(spark, [("x", 1, 2)])
    sqlfuncs.register(spark, {"hist": hist})
    assert spark.sql("select sp_inverse_variance(10, 1, 14, 3) as x, sum(cnt) as n from sp_hist").first()[0] == pytest.approx(11)
    spark.createDataFrame([("n", k, float(v)) for k, v in enumerate([3, 1, 2, 5, 4])], "node_id string, idx bigint, value double").createOrReplaceTempView("cells")
    got = spark.sql("select * from sp_isotonic(2, table(cells) partition by node_id order by idx)").orderBy("idx").collect()
    assert [r.fit for r in got] == [2, 2, 2, 4.5, 4.5]
    with pytest.raises(PermissionError):
        sqlfuncs.register(spark, truth={"hist": hist})


def test_release_questions(spark):
    hist = hist_of(spark, [("x", 0, 1), ("x", 1, 2), ("x", 5, 1)])
    s = release_queries.summary(hist).first()
    assert (s.n_groups, s.mean_size, s.share_of_ones) == (4, 1.75, 0.5)
    assert sorted((r.size, r.n) for r in release_queries.largest_groups(hist, 2).collect()) == [(1, 1), (5, 1)]
    assert release_queries.groups_at_least(hist, 1).first().n == 3
    assert release_queries.quantile_sizes(hist, [0.5]).first().q50 == 1


def test_readers_and_sinks(spark, tmp_path):
    hist = hist_of(spark, [("x", 1, 2)])
    tables.write_release(hist, str(tmp_path / "r"))
    assert spark.read.parquet(str(tmp_path / "r")).count() == 1
    hist.write.csv(str(tmp_path / "c"))
    assert tables.read_external(spark, str(tmp_path / "c"), "csv", "level int, node_id string, size long, cnt long").first().cnt == 2


def test_plans(spark):
    """Column pruning at the scan, counts before the join, a broadcast tree, no nested loops, whole-stage noise."""
    hist = WORKLOADS["w1"].histogram(spark, SF)[0]
    plan = hist._jdf.queryExecution().toString()
    physical = plan[plan.index("== Physical Plan") :]
    assert "l_discount" not in physical and "BroadcastHashJoin" in physical
    assert not re.search("CartesianProduct|BroadcastNestedLoop", physical)
    assert "partial_count" in physical
    noisy = spark.range(10).select(geometric_noise(1.0, "k", F.col("id")))._jdf.queryExecution().toString()
    assert "Python" not in noisy and "Arrow" not in noisy


def test_stage_meter(spark):
    from sizeprofile.plans.meter import StageMeter

    with StageMeter(spark, "count") as m:
        spark.range(100).repartition(3).count()
    assert m.seconds > 0 and m.jobs >= 1 and m.tasks >= 1 and m.to_df().count() == 1


def test_sorted_size_queries_at_all_nodes(spark):
    """hg_* against noise and min-max fits in plain Python, at every node of every level."""
    import hashlib
    import math
    from bisect import insort
    from collections import Counter

    from sizeprofile import queries

    rows = lambda name: Counter(map(tuple, queries.QUERIES[name](spark, SF).collect()))
    sizes = {}
    for level, node, size, n in sorted(map(tuple, WORKLOADS["w3"].histogram(spark, SF)[0].collect())):
        sizes.setdefault((level, node), []).extend((size, j) for j in range(1, n + 1))
    assert {k[0] for k in sizes} == {0, 1, 2}

    def noise(*key):
        u = [(int(hashlib.md5("|".join(map(str, (*key, c))).encode()).hexdigest()[:13], 16) + 0.5) / 2**52 for c in "ab"]
        return math.floor(math.log(u[0]) / -0.5) - math.floor(math.log(u[1]) / -0.5)

    def fit(x, p):
        best = [-math.inf] * len(x)
        for left in range(len(x)):
            seen, total, values = [], 0, []
            for v in x[left:]:
                total += v
                insort(seen, v)
                values.append(total / len(seen) if p == 2 else seen[(len(seen) - 1) // 2])
            low = math.inf
            for k in reversed(range(len(values))):
                low = min(low, values[k])
                best[left + k] = max(best[left + k], low)
        return [math.floor(max(v, 0) + 0.5) for v in best]

    cells, released = Counter(), {1: Counter(), 2: Counter()}
    for run, seed in queries.q.RUNS:
        for (level, node), order in sizes.items():
            noisy = [size + noise(seed, level, node, size, j) for size, j in order]
            cells.update((run, level, node, size, j, v) for (size, j), v in zip(order, noisy))
            for p in (1, 2):
                released[p].update((run, level, node, v, n) for v, n in Counter(fit(noisy, p)).items())
    assert Counter(map(tuple, queries.QUERIES["hg_noisy"](spark, SF).select("run_id", "level", "node_id", "size", "j", "noisy").collect())) == cells
    assert rows("hg_l1_release") == released[1]
    assert rows("hg_l2_release") == rows("hg_chunked_release") == released[2]
    assert rows("variance_hg") == Counter((*r, round(8.0 / r[4], 6)) for r in released[2])


def test_registered_experiments_have_ten_seeds(monkeypatch):
    import inspect

    from sizeprofile import queries

    for name, run in [*experiments.EXPERIMENTS.items()]:
        def seen(spark, sf_dir, of=inspect.signature(run), **given):
            bound = of.bind(spark, sf_dir, **given)
            bound.apply_defaults()
            return bound.arguments["seeds"]

        monkeypatch.setitem(experiments.EXPERIMENTS, name, seen)
        assert queries.QUERIES[f"exp_{name}"](None, "") == experiments.SEEDS == 10


def test_nonnegative_least_squares_against_a_plain_solver(spark):
    import random

    import numpy as np

    rnd = random.Random(4)
    paths = [(f"r{k // 4}", f"n{k}", f"s{k % 3}") for k in range(10)] + [("r0", "n0", "s7"), ("r9", "n77", "s1")]
    tree = RegionTree.from_levels(spark.createDataFrame(paths, "a string, b string, c string"), ["a", "b", "c"])
    nodes = [(r.level, r.node_id) for r in tree.nodes().collect()]
    leaves = sorted(n for level, n in nodes if level == 3)
    for spread in (3.0, 30.0):
        y = {node: rnd.gauss(1, spread) for node in nodes}
        got = {(r.level, r.node_id): r.x for r in release.nonnegative_least_squares(spark.createDataFrame([(*k, v) for k, v in y.items()], "level int, node_id string, y double"), tree).collect()}
        a = np.array([[float(n == "all" or leaf == n or leaf.startswith(n + "/")) for leaf in leaves] for _, n in nodes])
        goal, x = np.array([y[k] for k in nodes]), np.zeros(len(leaves))
        step = 1 / np.linalg.norm(a, 2) ** 2
        for _ in range(30_000):
            x = np.maximum(0, x + step * (a.T @ (goal - a @ x)))
        assert np.allclose([got[k] for k in nodes], a @ x, atol=1e-5)


def test_publish_pays_from_the_ledger(spark):
    from sizeprofile.functions.budget import BudgetExceeded

    hist, counts, tree = small(spark, EDGE)
    ledger = BudgetLedger(1.0)
    one = release.publish(hist, counts, tree, ledger, 0.6, ceiling=20)
    assert ledger.spent == pytest.approx(0.6) and len(ledger.entries) == 3
    assert [r.bad for r in metrics.audit(one.withColumn("run_id", F.lit(0)), counts, tree.nodes()).collect()] == [0, 0, 0, 0]
    assert one.collect() == one.collect()
    with pytest.raises(BudgetExceeded):
        release.publish(hist, counts, tree, ledger, 0.5, plan="bottom_up", ceiling=20)
    release.publish(hist, counts, tree, ledger, 0.3, plan="bottom_up", ceiling=20)
    sizes = hist.where("level = 0").select("size")
    assert release.private_ceiling(sizes, ledger, 0.05) > 90
    release.private_group_counts(counts, tree, "s", 0.05, ledger)
    assert ledger.spent == pytest.approx(1.0)
    with pytest.raises(BudgetExceeded):
        release.private_ceiling(sizes, ledger)


@pytest.mark.parametrize("p", [1, 2])
def test_fits_by_blocks_equal_plain_fits(spark, p):
    import random

    rnd = random.Random(p)
    rows = [(n, k, float(rnd.randint(0, 12) + k // 9)) for n in ("a", "b", "c") for k in range(150)]
    df = spark.createDataFrame(rows, "node_id string, idx long, v double")
    plain = {(r.node_id, r.idx): r.fit for r in isotonic.fit_by_node(df, ["node_id"], ["idx"], "v", p).collect()}
    for chunks in (1, 7):
        got = {}
        for b in isotonic.fit_chunked(df, ["node_id"], ["idx"], "v", chunks, p).collect():
            got.update({(b.node_id, b.idx + k): b.fit for k in range(b.cnt)})
        assert got.keys() == plain.keys() and all(abs(got[k] - plain[k]) < 1e-9 for k in plain)


def test_places_of_a_large_count_are_dealt_in_blocks(spark):
    hist = hist_of(spark, [("x", 3, 100), ("x", 5, 1), ("y", 0, 7)])
    got = profile.exploded(hist.select("node_id", "size", F.lit(4).cast("long").alias("first"), "cnt"), "place", block_rows=8)
    assert sorted((r.node_id, r.size, r.place) for r in got.collect()) == sorted((n, s, 4 + k) for n, s, c in [("x", 3, 100), ("x", 5, 1), ("y", 0, 7)] for k in range(c))
    assert got.groupBy("node_id", "size", "block").count().agg(F.max("count")).first()[0] == 8
    assert [r.idx for r in profile.to_sorted_sizes(hist).where("node_id = 'x'").orderBy("idx").collect()] == list(range(101))


def test_aggregates_by_name(spark):
    sqlfuncs.register(spark)
    spark.createDataFrame([("a", 1, 2, 0), ("a", 4, None, 1), ("a", 2, 0, 1), ("b", 3, 1, 1)], "g string, size long, t long, e long").createOrReplaceTempView("both_sides")
    got = {r.g: (r.d, r.m) for r in spark.sql("select g, sp_emd(size, t, e) as d, sp_lower_median(t) as m from both_sides group by g").collect()}
    assert got == {"a": (4, 0.0), "b": (0, 1.0)}


def test_cost_by_stage(spark):
    from sizeprofile.plans.meter import StageMeter

    with StageMeter(spark, "group") as m:
        spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().collect()
    rows = m.by_stage().collect()
    assert m.shuffle_bytes > 0 and sum(r.shuffle_written for r in rows) == m.shuffle_bytes and sum(r.rows_out for r in rows) >= 7


def test_tail_groups_draw_their_own_leaf(spark):
    """Groups of the cut size all lie in leaf c, with a tenth of the groups; new groups go where the groups are."""
    from sizeprofile.sources.synthetic_tail import extend_tail

    rows = [(f"{leaf}{k}", f"r/{leaf}", size(k)) for leaf, n, size in (("a", 1200, lambda k: 3), ("b", 600, lambda k: 3), ("c", 200, lambda k: 7 if k % 10 < 4 else 6)) for k in range(n)]
    sizes = spark.createDataFrame(rows, "group_id string, leaf_id string, size long")
    region = spark.createDataFrame([(f"r/{x}", "r") for x in "abc"], "leaf_id string, region string")
    out = extend_tail(sizes, region, "s", outliers=2000).cache()
    n = {(r.kind, r.leaf_id): r.n for r in out.groupBy(F.substring("group_id", 1, 1).alias("kind"), "leaf_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert abs(n["o", "r/a"] - 1200) < 120 and abs(n["o", "r/c"] - 200) < 70
    tail = out.where("group_id like 't%'")
    assert 100 < tail.count() < 240 and n["t", "r/a"] > 50 and n.get(("t", "r/c"), 0) < 40
    survive = [tail.where(F.col("size") == k).count() for k in (8, 9, 10)]
    assert 80 > survive[0] > survive[1] > survive[2]
    whole = spark.createDataFrame([(str(k), "r/a", 7) for k in range(5)], "group_id string, leaf_id string, size long")
    with pytest.raises(Exception, match="no finite tail"):
        extend_tail(whole, region, "s").collect()


def test_closed_periods_of_a_stream_are_the_sessions(spark, tmp_path):
    events = tables.load(spark, SF, "events").cache()
    last = events.agg(F.max("ts")).first()[0] + datetime.timedelta(days=50)
    closing = events.limit(1).withColumn("ts", F.lit(last).cast("timestamp_ntz")).withColumn("user_id", F.lit(-1).cast("long")).select(events.columns)
    for k, part in enumerate((events.where("event_id % 2 = 0"), events.where("event_id % 2 = 1"), closing, closing)):
        part.coalesce(1).write.parquet(str(tmp_path / f"p{k}"))
    (tmp_path / "in").mkdir()
    schema = ", ".join(events.schema.simpleString()[7:-1].replace(":", " ").split(","))
    source = stream.events_stream(spark, str(tmp_path / "in"), schema)
    q = stream.closed_sizes(source, lateness="40 days").writeStream.outputMode("append").format("memory").queryName("closed").start()
    for k in range(4):
        for f in (tmp_path / f"p{k}").glob("*.parquet"):
            f.rename(tmp_path / "in" / f"{k}-{f.name}")
        q.processAllAvailable()
        assert k > 1 or spark.table("closed").count() == 0
    q.stop()
    got = sorted((r.user_id, r.begin, r.size) for r in spark.table("closed").collect())
    assert got == sorted((r.user_id, r.session.start, r.size) for r in stream.session_sizes(events).collect())


def test_sorted_sizes_by_law_have_the_law_of_the_fit():
    from collections import Counter
    from itertools import permutations

    import numpy as np

    from sizeprofile.functions.isotonic import isotonic_l2, pooled_means
    from sizeprofile.functions.noise import geometric_faces

    def cycles(p):
        left = set(range(len(p)))
        while left:
            at, cycle = min(left), []
            while at in left:
                left.remove(at)
                cycle.append(at)
                at = p[at]
            yield cycle

    for x in ([3, -1, 2, 7], [0, 0, 1, 5, -2], [1, 1, 0, 0, 2, 2]):
        orders = list(permutations(range(len(x))))
        fits = Counter(tuple(np.round(isotonic_l2([x[k] for k in p]), 9)) for p in orders)
        cut = Counter(tuple(np.round(np.concatenate([[m] * n for m, n in sorted((np.mean([x[k] for k in c]), len(c)) for c in cycles(p))]), 9)) for p in orders)
        assert fits == cut
    rng, truth, errors = np.random.default_rng(5), [(0, 20), (1, 60), (2, 40), (5, 5)], ([], [])
    values = np.repeat([a for a, _ in truth], [n for _, n in truth])
    p = 1 - np.exp(-0.5)
    for _ in range(800):
        drawn = isotonic_l2(values + rng.geometric(p, len(values)) - rng.geometric(p, len(values)))
        faces = [geometric_faces(n, a, 2.0, rng) for a, n in truth]
        assert [c.sum() for _, c in faces] == [n for _, n in truth]
        t, c = pooled_means(*(np.concatenate(x).astype(float) for x in zip(*faces)))
        for fit, error in zip((drawn, np.repeat(t / c, c.astype(int))), errors):
            error.append(np.abs(np.floor(np.maximum(fit, 0) + 0.5) - values).sum())
    gap = abs(np.mean(errors[0]) - np.mean(errors[1]))
    assert gap < 5 * np.sqrt(sum(np.var(e) / len(e) for e in errors))


def test_experiments_draw_sorted_sizes_of_very_many_groups(spark):
    runs = estimators.runs_table(spark, [(0, "a", 0.1), (1, "b", 0.5)])
    hist = spark.createDataFrame([(0, "all", 0, 7), (0, "all", 1, 3_000_000_000), (0, "all", 4, 2_000_000_000)], "level int, node_id string, size long, cnt long")
    got = estimators.estimate_sorted_faces(hist, runs)
    assert {r.run_id: r.n for r in got.groupBy("run_id").sum("cnt").withColumnRenamed("sum(cnt)", "n").collect()} == {0: 5_000_000_007, 1: 5_000_000_007}
    near = {(r.run_id, r.size): r.cnt for r in got.collect()}
    assert near[1, 1] > 2_999_000_000 and near[1, 4] > 1_999_000_000


def test_three_levels_has_every_workload_at_every_budget_and_root(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(experiments, "inputs", lambda spark, d, w, nodes=None: (w, nodes, None, 64))
    monkeypatch.setattr(experiments, "evaluate", lambda spark, w, nodes, t, rel, eps, seeds: seen.append((w, nodes is None, eps)) or spark.range(1))
    assert experiments.three_levels(spark, "").count() == 10
    assert sorted(seen) == sorted((w, full, (0.1, 0.5)) for w in ("w1", "w2", "w3", "w4", "w5") for full in (True, False))


def test_experiments_read_the_tables_once(spark, monkeypatch):
    rows = lambda df: sorted(map(tuple, df.collect()))
    read, frozen = [], release.frozen
    monkeypatch.setattr(release, "frozen", lambda df: read.append(any("orders.parquet" in f for f in df.inputFiles())) or frozen(df))
    for w, nodes in (("w1", None), ("w3", ["ASIA", "EUROPE"]), ("w5", ["AMERICA"])):
        read.clear()
        hist, counts, tree, ceiling = experiments.inputs(spark, SF, w, nodes=nodes)
        assert sum(read) == 1
        entities, groups, whole = WORKLOADS[w].load(spark, SF)
        if nodes:
            whole = whole.restrict(nodes)
            groups = groups.join(whole.wide.select("leaf_id"), "leaf_id", "left_semi")
        sizes = profile.clamp_sizes(profile.group_sizes(entities, groups), ceiling)
        assert rows(tree.wide.select(*whole.wide.columns)) == rows(whole.wide)
        assert rows(hist) == rows(profile.rollup_histogram(profile.leaf_histogram(sizes), whole).select(*hist.columns))
        assert rows(counts) == rows(profile.public_counts(groups, whole).select(*counts.columns))


def test_fits_of_a_sweep_are_dealt_over_tasks_and_nodes_may_span_batches(spark):
    hist, counts, _, _ = experiments.inputs(spark, SF, "w1")
    runs, _ = experiments.run_grid(spark, (0.1, 0.5), 10)
    for fit in (lambda: estimators.estimate_cumulative(hist, counts, runs, 64), lambda: estimators.estimate_sorted_faces(hist, runs)):
        got = fit().withColumn("task", F.spark_partition_id())
        assert got.select("task").distinct().count() > 1
        assert got.groupBy(*estimators.KEYS).agg(F.countDistinct("task").alias("n")).where("n > 1").count() == 0
        assert fit().groupBy(*estimators.KEYS).agg(F.sum("cnt").alias("s")).join(counts, ["level", "node_id"]).where("s = g").count() == 20 * counts.where("g > 0").count()
        once = sorted(map(tuple, fit().collect()))
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
        try:
            assert sorted(map(tuple, fit().collect())) == once
        finally:
            spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_errors_of_known_runs_are_evaluated_once(spark):
    hist, counts, _, _ = experiments.inputs(spark, SF, "w1")
    runs, _ = experiments.run_grid(spark, (0.5,), 3)
    errors = metrics.emd(metrics.for_runs(hist, runs), estimators.estimate_cumulative(hist, counts, runs, 64))
    report = metrics.level_report(errors, counts, runs)
    assert report._jdf.queryExecution().optimizedPlan().toString().count("MapInPandas") == 1
    assert sorted(map(tuple, report.collect())) == sorted(map(tuple, metrics.level_report(errors, counts).collect()))


def test_budget_sweep_has_every_workload_at_every_budget(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(experiments, "inputs", lambda spark, d, w: (w, None, None, 64))
    monkeypatch.setattr(experiments, "evaluate", lambda spark, w, c, t, rel, eps, seeds: seen.append((w, tuple(rel), eps, seeds)) or spark.range(1))
    assert experiments.budget_sweep(spark, "").count() == 4
    assert sorted(seen) == [(w, ("hc", "hg", "bottom_up"), (0.05, 0.1, 0.2, 0.5, 1.0), 10) for w in ("w1", "w3", "w4", "w5")]
