"""The methods against closed forms, identities, laws and each other."""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from nodeflux.functions import params as pm
from nodeflux.functions import rng
from nodeflux.functions.params import Params
from nodeflux.functions.rng import u01_fast, u01_md5, u01_np
from nodeflux.operators import accuracy, bidirectional, exact, graph, push, resident, reverse, walks, workloads
from nodeflux.operators.push import adaptive_push, amplified
from nodeflux.operators.targets import degree_targets, stratified_targets, uniform_targets

P = Params()


def make(spark, pairs, isolated=()):
    raw = spark.createDataFrame([(f"x:{a:04d}", f"x:{b:04d}") for a, b in pairs], "a string, b string")
    lone = spark.createDataFrame([(f"x:{i:04d}",) for i in isolated], "key string") if isolated else None
    return graph.build(raw, lone)


def star(k):
    return [(0, i) for i in range(1, k + 1)]


def targets(spark, *nodes):
    return spark.createDataFrame(list(enumerate(nodes)), "qid int, t long")


@pytest.fixture(scope="module")
def tree(spark, sf):
    return graph.graph(spark, sf, "tree")


@pytest.fixture(scope="module")
def purchase(spark, sf):
    return graph.graph(spark, sf, "purchase")


def test_uniforms_are_keyed_and_inside(spark):
    rows = spark.range(2000).select(u01_md5(F.lit(1), F.col("id")).alias("a"), u01_fast(1, F.col("id")).alias("b")).toPandas()
    for c in "ab":
        assert rows[c].between(0, 1, inclusive="neither").all() and abs(rows[c].mean() - 0.5) < 0.03
    assert np.allclose(rows["b"], u01_np(1, np.arange(2000)), atol=0)


def test_dirty_graph_is_cleaned(spark):
    rows = [("x:1", "x:2"), ("x:2", "x:1"), ("x:1", "x:2"), ("x:3", "x:3"), (None, "x:1"), ("x:1", None), ("x:2", "x:4")]
    g = graph.build(spark.createDataFrame(rows, "a string, b string"))
    assert g.stats == graph.Stats(3, 2, 2)
    assert Counter(map(tuple, g.edges.select("src", "dst", "pos", "src_deg", "dst_deg").collect())) == Counter(
        [(0, 1, 1, 1, 2), (1, 0, 1, 2, 1), (1, 2, 2, 2, 1), (2, 1, 1, 1, 2)]
    )


def test_positions_of_a_hub_in_chunks(spark, monkeypatch):
    monkeypatch.setattr(graph, "CHUNK", 7)
    g = make(spark, star(50))
    assert sorted(r.pos for r in g.edges.filter("src = 0").collect()) == list(range(1, 51))
    assert [r.pos for r in g.edges.filter("src = 0").orderBy("dst").collect()] == list(range(1, 51))


@pytest.mark.parametrize("k", [3, 40])
def test_star_closed_form(spark, k):
    g, a, n = make(spark, star(k)), P.alpha, k + 1
    centre = (a / n + (1 - a) * k * a / n) / (1 - (1 - a) ** 2)
    leaf = (1 - a) * centre / k + a / n
    got = {r.node: r.pi for r in exact.power_iteration(g, P, 80).collect()}
    assert math.isclose(got[0], centre, rel_tol=1e-6) and math.isclose(got[1], leaf, rel_tol=1e-6)
    assert math.isclose(sum(got.values()), 1, rel_tol=1e-9)
    est = {r.t: r.pagerank for r in adaptive_push(g, targets(spark, 0, 1), P, theta=0.0, hops=60, sampler="edge").df.collect()}
    assert math.isclose(est[0], centre, rel_tol=1e-4) and math.isclose(est[1], leaf, rel_tol=1e-4)


@pytest.mark.parametrize("pairs", [[(i, j) for i in range(6) for j in range(i)], [(i, (i + 1) % 7) for i in range(7)], [(0, 1)], [(0, 1), (2, 3)]])
def test_regular_graphs_are_uniform(spark, pairs):
    g = make(spark, pairs)
    for r in exact.power_iteration(g, P, 5).collect():
        assert math.isclose(r.pi, 1 / g.stats.n, rel_tol=1e-9)


def test_isolated_nodes_keep_their_share(spark):
    g = make(spark, [(0, 1)], isolated=[5])
    got = {r.node: r.pi for r in exact.power_iteration(g, P, 4).collect()}
    assert math.isclose(got[2], 1 / 3) and math.isclose(sum(got.values()), 1)
    assert math.isclose(adaptive_push(g, targets(spark, 2), P, hops=3).df.first().pagerank, 1 / 3)


def test_engine_choice(spark, tree, monkeypatch):
    from nodeflux.operators.estimate import choose_engine, single_node_pagerank

    t = uniform_targets(tree, 3)
    assert choose_engine(tree, t, P) == "resident"
    near = {r.t: r.pagerank for r in single_node_pagerank(tree, t, P).collect()}
    truth = {r.node: r.pi for r in workloads.truth(tree, P).collect()}
    assert all(abs(v - truth[k]) <= P.c * truth[k] for k, v in near.items())
    monkeypatch.setattr(resident, "RESIDENT_EDGES", 10)
    assert choose_engine(tree, t, P) == "exact" and choose_engine(tree, t.limit(0), P) == "distributed"


def test_bad_targets(spark, tree):
    assert adaptive_push(tree, targets(spark, 10**9), P, hops=2).df.count() == 0
    assert adaptive_push(tree, targets(spark).limit(0) if False else spark.createDataFrame([], "qid int, t long"), P, hops=2).df.count() == 0
    twice = adaptive_push(tree, targets(spark, 3, 3), P, theta=0.0, hops=4, sampler="edge").df.collect()
    assert len(twice) == 2 and math.isclose(twice[0].pagerank, twice[1].pagerank, rel_tol=1e-12)


def test_exact_push_equals_truncated_pagerank(spark, purchase):
    t = uniform_targets(purchase, 4)
    full = {r.node: r.pi for r in exact.truncated_pagerank(purchase, P, 5).collect()}
    for r in adaptive_push(purchase, t, P, theta=0.0, hops=5, sampler="edge").df.collect():
        assert math.isclose(r.pagerank, full[r.t], rel_tol=1e-9)


def test_hop_sums_and_reversibility(spark, purchase):
    t = uniform_targets(purchase, 3)
    for ell in (0, 2):
        sums = exact.hop_ppr(purchase, t, ell, P).groupBy("qid").agg(F.sum("value").alias("s")).collect()
        assert all(math.isclose(r.s, P.alpha * (1 - P.alpha) ** ell, rel_tol=1e-9) for r in sums)
    gaps = exact.reversibility_gap(purchase, exact.ppr_from(purchase, t, P, 4), t).collect()
    assert all(r.gap < 1e-12 for r in gaps)


def test_lower_bounds_hold(spark, purchase):
    pi = exact.power_iteration(purchase, P, 40).withColumn("npi", F.col("pi") * purchase.stats.n)
    worst = exact.lower_bounds(purchase, P).join(pi, "node").agg(*[F.min(F.col("npi") / F.col(c)).alias(c) for c in ("by_teleport", "by_edges")]).first()
    assert min(worst) >= 1 - 1e-6


def test_truncation_and_convergence(spark, tree):
    hops = pm.hop_cap(tree.stats.n, P)
    csr = resident.csr(tree)
    truth = tree.spark.createDataFrame(list(enumerate(map(float, resident.power(csr, P, 200)))), "node long, pi double")
    gap = accuracy.truncation_gap(truth, exact.truncated_pagerank(tree, P, hops)).first()
    assert -1e-12 <= gap.least and gap.most <= P.c * P.alpha / (2 * tree.stats.n)
    assert all(r.ratio is None or r.ratio <= 1 - P.alpha + 1e-9 for r in exact.convergence(tree, P, 5).collect())


@pytest.mark.parametrize("sampler", ["edge", "skip"])
def test_resident_equals_distributed(spark, purchase, sampler):
    t = uniform_targets(purchase, 3)
    far = {r.qid: r for r in adaptive_push(purchase, t, P, theta=2e-3, hops=5, sampler=sampler, seed=5).df.collect()}
    near = resident.resident(purchase, workloads.jobs(t, ("adaptive_push",)), P, theta=2e-3, hops=5, sampler=sampler, seed=5).collect()
    for r in near:
        assert math.isclose(r.pagerank, far[r.qid].pagerank, rel_tol=1e-9)
        assert (r.increments, r.exact_increments, r.draws) == (far[r.qid].increments, far[r.qid].exact_increments, far[r.qid].draws)


def plain_push(lists, t, theta, hops, sampler, seed, qid):
    """(pagerank, increments, exact increments, draws) by loops over nodes and places, from the keyed draws alone."""
    n, front, total, paid, exact_paid, draws = len(lists), {t: 1.0}, 0.0, 0, 0, 0
    for hop in range(hops + 1):
        total += sum(P.alpha * len(lists[t]) * r / (n * len(lists[v])) for v, r in front.items())
        if hop == hops:
            break
        after = {}
        for v, r in front.items():
            share, deg = (1 - P.alpha) * r / len(lists[v]), len(lists[v])
            places, inc = range(deg), share
            if share >= theta:
                exact_paid += deg
            elif sampler == "skip":
                inc, places, at, k = theta, [], -1, 0
                while at < deg:
                    u = float(u01_np(seed, hop, qid, 0, v, k))
                    at += 1 + math.floor(math.log(u) / math.log1p(-share / theta))
                    k += 1
                    places += [at] if at < deg else []
                draws += k
            else:
                rng = np.random.default_rng([seed, hop, qid, 0, v])
                k = rng.binomial(deg, share / theta)
                inc, places = theta, rng.choice(deg, size=k, replace=False).tolist()
                draws += 1 + k
            for at in places:
                after[lists[v][at]] = after.get(lists[v][at], 0.0) + inc
            paid += len(places)
        front = after
    return total, paid, exact_paid, draws


@pytest.mark.parametrize("sampler", ["skip", "binomial"])
def test_samplers_equal_a_plain_version(spark, sf, sampler):
    g = graph.graph(spark, sf, "supply")
    lists = [[] for _ in range(g.stats.n)]
    for r in g.edges.select("src", "pos", "dst").orderBy("src", "pos").collect():
        lists[r.src].append(r.dst)
    for r in adaptive_push(g, uniform_targets(g, 4), P, theta=5e-3, hops=9, sampler=sampler, seed=3).df.collect():
        want = plain_push(lists, r.t, 5e-3, 9, sampler, 3, r.qid)
        assert math.isclose(r.pagerank, want[0], rel_tol=1e-9) and (r.increments, r.exact_increments, r.draws) == want[1:]


@pytest.mark.parametrize("sampler", ["edge", "skip", "binomial"])
def test_wide_frontiers_give_the_same_answers(spark, tree, monkeypatch, sampler):
    """Beyond the broadcast bound hops shuffle: same estimates, increments and draws."""
    t, runs = uniform_targets(tree, 3), []
    for bound in (push.BROADCAST_ROWS, 0):
        monkeypatch.setattr(push, "BROADCAST_ROWS", bound)
        got = push.adaptive_push(tree, t, P, theta=0.02, hops=4, sampler=sampler, seed=5, reps=2).df
        runs.append(sorted((r.qid, r.rep, round(r.pagerank, 12), r.increments, r.exact_increments, r.draws) for r in got.collect()))
    assert runs[0] == runs[1] and any(r[5] for r in runs[0])


def test_table_is_counted_while_it_is_written(spark):
    from nodeflux.plans.storage import cut_counted

    for rows in (1000, 0):
        held, seen = cut_counted(spark.range(rows).repartition(4), "counted", [F.count("id").alias("rows"), F.coalesce(F.max("id"), F.lit(-1)).alias("last")])
        assert (held.count(), held.count(), rows - 1) == (rows, seen["rows"], seen["last"])


def test_no_hops_is_not_the_cap(spark, purchase):
    t = uniform_targets(purchase, 2)
    rows = resident.resident(purchase, workloads.jobs(t, ("adaptive_push",)), P, hops=0).collect()
    assert all(math.isclose(r.pagerank, P.alpha / purchase.stats.n) and r.increments == 0 for r in rows)


@pytest.mark.parametrize("name", ["purchase", "supply", "tree", "links"])
def test_blanket_method_is_within_c(spark, sf, name):
    """Nine targets of ten within c, from either side."""
    c = resident.csr(graph.graph(spark, sf, name))
    truth = resident.power(c, P, 100)
    rng = np.random.default_rng(5)
    nodes = rng.choice(c.n, 12, replace=False).tolist()
    errors = [resident.two_phase(c, t, P, "blanket_bidirectional", 1)[0] / truth[t] - 1 for t in nodes]
    assert sum(abs(e) <= P.c for e in errors) >= 11, errors


def test_hops_over_a_store_read_the_frontiers_buckets(spark, tree, tmp_path):
    tree.write(str(tmp_path / "g"), 16)
    back = graph.Graph.open(spark, str(tmp_path / "g"))
    front = spark.createDataFrame([(3,), (9,)], "node long")
    plan = back.around(front)._jdf.queryExecution().executedPlan().toString()
    assert "bucket" in plan.split("PartitionFilters: [")[1].split("]")[0]
    want = {(r.src, r.dst, r.pos) for r in tree.edges.filter("src in (3, 9)").collect()}
    assert {(r.src, r.dst, r.pos) for r in back.around(front).filter("src in (3, 9)").collect()} == want
    assert back.around(front).count() < tree.edges.count()
    t = uniform_targets(tree, 3)
    near = {r.t: (r.pagerank, r.increments, r.draws) for r in adaptive_push(tree, t, P, theta=1e-2, hops=4).df.collect()}
    far = {r.t: (r.pagerank, r.increments, r.draws) for r in adaptive_push(back, t, P, theta=1e-2, hops=4).df.collect()}
    assert all(math.isclose(near[k][0], far[k][0], rel_tol=1e-12) and near[k][1:] == far[k][1:] for k in near)


@pytest.mark.parametrize(("sampler", "theta"), [("edge", 5e-2), ("skip", 1e-2), ("skip", 5e-2)])
def test_push_is_unbiased_and_within_cost(spark, purchase, sampler, theta):
    c = resident.csr(purchase)
    t, reps, hops = 7, 400, 40
    runs = np.array([resident.push_query(c, t, theta, hops, P, sampler, 1, 0, rep)[:2] for rep in range(reps)])
    truth = resident.push_query(c, t, 0.0, hops, P, "edge", 0, 0, 0)[0]
    mean, error = runs[:, 0].mean(), runs[:, 0].std(ddof=1) / math.sqrt(reps)
    assert abs(mean - truth) < 4 * error
    bound = (1 - P.alpha) / (P.alpha * theta)
    assert runs[:, 1].mean() <= bound + 3 * runs[:, 1].std(ddof=1) / math.sqrt(reps)
    assert runs[:, 0].var(ddof=1) <= hops * theta * c.deg[t] / c.n * truth


def test_variance_falls_with_theta(spark, purchase):
    c = resident.csr(purchase)
    spread = [np.var([resident.push_query(c, 3, theta, 30, P, "skip", 2, 0, rep)[0] for rep in range(150)]) for theta in (5e-2, 5e-3)]
    assert spread[1] < spread[0] / 2


def test_samplers_agree_in_law(spark):
    from nodeflux.operators.push import next_residue

    g = make(spark, star(12))
    residue = spark.range(3000).select(
        F.lit(0).alias("qid"), F.col("id").cast("int").alias("rep"), F.lit(0.25).alias("theta"), F.lit(12).cast("long").alias("t_deg"),
        F.lit(0).cast("long").alias("node"), F.lit(12).cast("long").alias("deg"), F.lit(1.0).alias("r"),
    )
    want = 3000 * (0.8 / 12) / 0.25
    for sampler in ("edge", "skip", "binomial"):
        held = {r.node: r.n for r in next_residue(g, residue, P, 0, 9, sampler, "fast").filter("node is not null").groupBy("node").agg(F.count("*").alias("n")).collect()}
        assert len(held) == 12 and all(abs(n - want) < 5 * math.sqrt(want) for n in held.values())


def test_accuracy_of_the_schedule(spark, purchase):
    rows = workloads.run_query_set(spark, "/root/testdata/sf0.001", ["purchase"], ("adaptive_push",), "uniform", P.but(c=0.5), k=5, reps=4).collect()
    assert np.mean([r.error_over_c > 1 for r in rows]) <= P.pf
    assert all(r.increments <= 12 / 0.3 * pm.hop_cap(purchase.stats.n, P.but(c=0.5)) / (0.04 * 0.25) * r.deg for r in rows)


def test_reverse_push_underestimates_by_eps(spark, tree):
    t = uniform_targets(tree, 3)
    state = reverse.reverse_push(tree, t, P, 0.02)
    for r in accuracy.reserve_gap(exact.ppr_to(tree, t, P, 60), state).collect():
        assert -1e-6 <= r.least and r.most <= 0.02 + 1e-9
    first = {r.qid: r.p for r in reverse.reverse_push(tree, t, P, 0.05, order="priority", batch=4).groupBy("qid").agg(F.sum("p").alias("p")).collect()}
    c = resident.csr(tree)
    for r in t.collect():
        strict = resident.reverse_query(c, r.t, 0.05, P, priority=True)[0].sum()
        assert abs(first[r.qid] - strict) < 0.25 * strict + 0.05 * tree.stats.n
        assert state.filter(f"qid = {r.qid} and r >= 0.02").isEmpty()


def test_randomized_reverse_push_matches_resident_and_contrast(spark):
    g = make(spark, star(300))
    t = targets(spark, 0)
    far = reverse.randomized_reverse_push(g, t, P, 5e-3, "edge", 4, seed=3).first()
    near = resident.randomized_query(resident.csr(g), 0, 5e-3, 4, P, "edge", 3, 0, 0)
    assert math.isclose(far.pagerank, near[0], rel_tol=1e-9) and far.increments == near[1]
    # what each child would get lies below theta, so one shared draw pays all children or none
    c = resident.csr(make(spark, star(60) + [(i, 100 * i + j) for i in range(1, 61) for j in range(20)]))
    runs = {d: np.array([resident.randomized_query(c, 0, 0.05, 6, P, d, 1, 0, rep)[0] for rep in range(200)]) for d in ("shared", "edge")}
    assert runs["shared"].var() > 3 * runs["edge"].var()


def test_walks_and_two_phase_methods(spark, tree):
    c, t, p = resident.csr(tree), uniform_targets(tree, 4), P.but(alpha=0.5)  # short walks, few steps
    truth = resident.power(c, p, 100)
    stats = walks.walk_length_stats(walks.walk_ends(tree, 3000, p, None, 1), p).first()
    assert abs(stats.mean_moves - 1) < 0.15 and stats.walks == 3000
    got = {r.t: r.pagerank for r in walks.walk_sample(tree, t, p, 20_000, seed=2).collect()}
    assert all(abs(v - truth[k]) < 6 * math.sqrt(truth[k] / 20_000) for k, v in got.items())
    for method in (bidirectional.residue_bidirectional, bidirectional.subgraph_walks):
        for r in method(tree, t, p, n_walks=8000).collect():
            assert abs(r.pagerank - truth[r.t]) < 0.25 * truth[r.t] + 1e-4
    for r in bidirectional.blanket_bidirectional(tree, t, p, n_walks=8000).collect():
        assert abs(r.pagerank - truth[r.t]) <= 0.25 * truth[r.t] + 1e-4


def test_amplification(spark, tree):
    assert pm.amplification(1e-3) == 125
    est = adaptive_push(tree, uniform_targets(tree, 2), P, theta=0.05, hops=8, reps=9).df
    one = {r.qid: r.pagerank for r in amplified(est).collect()}
    rows = {q: sorted(r.pagerank for r in est.filter(f"qid = {q}").collect()) for q in one}
    assert all(math.isclose(one[q], rows[q][4]) for q in one)
    assert amplified(est, groups=3).count() == 2


def test_query_sets(spark, purchase):
    assert uniform_targets(purchase, 10, 1).count() == 10
    d = degree_targets(purchase, 10, 1).collect()
    assert len({r.t for r in d}) == 10
    mean = np.mean([r.deg for s in range(15) for r in degree_targets(purchase, 10, s).join(purchase.nodes, F.col("t") == F.col("node")).collect()])
    assert mean > purchase.stats.avg_deg
    for r in stratified_targets(purchase, 3).join(purchase.nodes, F.col("t") == F.col("node")).collect():
        low = dict(zip(("huge", "large", "above", "below", "small"), (100, 10, 1, 0.1, 0.01), strict=True))[r.stratum]
        assert r.deg >= low * purchase.stats.avg_deg


def test_partition_count_does_not_change_results(spark, sf):
    before, seen = spark.conf.get("spark.sql.shuffle.partitions"), []
    try:
        for n in ("1", "5", "17"):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            g = graph.build(graph.GRAPHS["tree"](spark, sf))
            rows = adaptive_push(g, uniform_targets(g, 3), P, theta=0.02, hops=5, sampler="edge").df.orderBy("qid").collect()
            seen.append([(r.t, round(r.pagerank, 12), r.increments) for r in rows])
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert seen[0] == seen[1] == seen[2]


def test_store_prunes_partitions(spark, tree, tmp_path):
    tree.write(str(tmp_path / "g"), 16)
    back = graph.Graph.open(spark, str(tmp_path / "g"))
    assert back.stats == tree.stats
    part = graph.pruned(spark.read.parquet(str(tmp_path / "g/adj")), [3, 9], 16)
    plan = part._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in plan and "bucket" in plan.split("PartitionFilters: [")[1].split("]")[0]
    assert {r.src for r in part.collect()} <= {3, 9}


def test_plans_broadcast_small_frontiers_and_prune_columns(spark, sf):
    from nodeflux.sources.graphs import purchase as raw

    plan = raw(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "o_totalprice" not in plan and "l_quantity" not in plan


def test_sweep_cut_finds_the_component(spark):
    g = make(spark, [(i, j) for i in range(5) for j in range(i)] + [(10 + i, 10 + j) for i in range(6) for j in range(i)] + [(0, 10)])
    got = accuracy.sweep_cut(g, exact.ppr_from(g, targets(spark, 2), P, 20)).first()
    assert (got.size, got.cut) == (5, 1)


def test_components(spark):
    g = make(spark, [(0, 1), (1, 2), (5, 6), (6, 7), (7, 8), (8, 9), (9, 5)])
    assert Counter(r.comp for r in graph.components(g).collect()) == Counter({0: 3, 3: 5})


def test_query_sets_run_every_method(spark):
    """Also the subgraph method, which had no resident form, and without bias."""
    rows = workloads.run_query_set(spark, "/root/testdata/sf0.001", ["links"], workloads.METHODS, "uniform", P.but(c=0.5), k=3).collect()
    assert {r.method for r in rows} == set(workloads.METHODS) and len(workloads.METHODS) == 9
    c = resident.csr(graph.graph(spark, "/root/testdata/sf0.001", "supply"))
    truth = resident.power(c, P, 100)[3]
    runs = np.array([resident.subgraph_query(c, 3, P, seed, 0)[0] for seed in range(60)])
    assert abs(runs.mean() - truth) < 4 * runs.std(ddof=1) / math.sqrt(60)


def test_two_phase_methods_take_their_own_number_of_walks(spark, sf):
    g, p = graph.graph(spark, sf, "tree"), Params(alpha=0.8, c=0.2)  # short walks, few steps
    t = uniform_targets(g, 3)
    truth = resident.power(resident.csr(g), p, 100)
    degs = {r.t: r.deg for r in t.join(g.nodes, F.col("t") == F.col("node")).collect()}
    n, most = g.stats.n, max(degs.values())
    rows = bidirectional.residue_bidirectional(g, t, p).collect()
    limit = p.c * math.sqrt(p.alpha * most / (n * math.log(1 / p.pf)))
    assert all(r.increments >= math.ceil((2 * p.c / 3 + 2) * limit * n / (p.c**2 * p.alpha) * math.log(2 / p.pf)) for r in rows)
    assert all(abs(r.pagerank - truth[r.t]) <= p.c * truth[r.t] for r in rows)
    want = g.nodes.agg(F.max(pm.blanket_walks(F.lit(most), n, p))).first()[0]
    assert bidirectional.most_walks(g, t, pm.blanket_walks(F.col("deg"), n, p)) == want > 10_000
    ends = walks.walk_ends(g, 3000, p, None, 1)
    assert ends.count() == 3000


def test_resident_blanket_walks_are_not_clipped(spark):
    c = resident.csr(make(spark, star(600)))
    want = 45 * pm.hop_cap(c.n, P) / P.c * math.sqrt(c.n * 600 * math.log(1.25) * math.log(20) / (P.alpha * math.log(c.n / P.alpha)))
    assert want > 2_000_000 and resident.two_phase(c, 0, P, "blanket_bidirectional", 0)[1] >= want


def test_baselines_run_by_their_own_formulas(spark, sf):
    from nodeflux.queries import QUERIES

    n = graph.graph(spark, sf, "supply").stats.n
    for r in QUERIES["baseline_walk_sample"](spark, sf).filter("graph = 'supply'").collect():
        assert r.increments == pm.walk_count(P, P.alpha / n) and r.error_over_c <= 1
    for name in ("baseline_reverse_push", "baseline_residue_bidirectional"):
        assert all(r.error_over_c <= 1 for r in QUERIES[name](spark, sf).collect())


def test_error_report_measures_the_method_and_not_a_cut(spark, sf):
    from nodeflux.queries import QUERIES

    for r in QUERIES["relative_error_report_whole"](spark, sf).collect():
        assert r.max_error_over_c <= 1 and r.failure_rate == 0 and r.queries == 10
    n = graph.graph(spark, sf, "supply").stats.n
    mass = QUERIES["truncated_pagerank_whole"](spark, sf).agg(F.sum("n_pi")).first()[0]
    assert 1 - P.c * P.alpha / 2 - 1e-4 <= mass / n <= 1 + 1e-4


def test_large_graphs_take_the_distributed_plans(spark, sf, monkeypatch):
    g, p = graph.graph(spark, sf, "links"), Params(alpha=0.8, c=0.5)
    t = uniform_targets(g, 2)
    near = {(r.method, r.t): r for r in workloads.answers(g, t, workloads.METHODS, p).collect()}
    monkeypatch.setattr(resident, "RESIDENT_EDGES", 10)
    far = {(r.method, r.t): r for r in workloads.answers(g, t, workloads.METHODS, p).collect()}
    assert set(near) == set(far) and len(far) == 18
    for method in ("adaptive_push", "power_iteration", "reverse_push"):
        for r in t.collect():
            assert math.isclose(far[method, r.t].pagerank, near[method, r.t].pagerank, rel_tol=1e-6)
    assert all(r.mean_error < 1 for r in workloads.sweep(g, t, [1e-3], p, 1).collect())


def test_neighbours_in_blocks_equal_all_pairs(spark, sf, monkeypatch):
    from nodeflux.sources import graphs

    whole = Counter(map(tuple, graphs.knn(spark, sf).collect()))
    monkeypatch.setattr(graphs, "KNN_VECTORS", 300)
    assert Counter(map(tuple, graphs.knn(spark, sf).collect())) == whole


def test_keyed_draws_are_those_of_the_engine(spark):
    got = spark.range(5).select(rng.u01_md5(3, F.col("id"), 7)).toPandas().iloc[:, 0].to_numpy()
    assert np.array_equal(got, rng.u01_md5_np(3, np.arange(5), 7))


@pytest.mark.parametrize("deg,chance", [(1, 0.5), (30, 1e-9), (200, 0.37), (558, 0.999)])
def test_binomial_law_sums_to_one(deg, chance):
    law = push.binomial_law(deg, chance)
    assert math.isclose(law.sum(), 1, rel_tol=1e-9) and math.isclose((law * np.arange(deg + 1)).sum(), deg * chance, rel_tol=1e-9)


@pytest.mark.parametrize("sampler", ["skip", "edge"])
def test_kernel_repeats_keyed_draws(spark, tree, sampler):
    t = uniform_targets(tree, 3)
    far = {r.qid: r for r in adaptive_push(tree, t, P, theta=2e-2, hops=4, sampler=sampler, seed=5, coin="md5").df.collect()}
    near = resident.resident(tree, workloads.jobs(t, ("adaptive_push",)), P, theta=2e-2, hops=4, sampler=sampler, seed=5, coin="md5").collect()
    assert near and all((r.increments, r.draws) == (far[r.qid].increments, far[r.qid].draws) for r in near)


def test_cost_of_a_run(spark, tmp_path):
    from nodeflux.plans.cost import spark_cost

    spark.range(1000).withColumn("k", F.col("id") % 7).write.parquet(str(tmp_path / "t"))
    rows = spark.read.parquet(str(tmp_path / "t"))
    plain, grouped = spark_cost(spark, lambda: rows), spark_cost(spark, lambda: rows.groupBy("k").agg(F.sum("id")))
    assert plain.rows_read == grouped.rows_read == 1000 and plain.shuffle_bytes == 0 < grouped.shuffle_bytes
    assert plain.jobs >= 1 and plain.bytes_read > 0 and plain.spilled_bytes == 0


def test_median_of_means_leaves_nulls_out(spark):
    from nodeflux.functions import udaf

    udaf.register(spark)
    spark.createDataFrame([(1, 1.0, 0), (1, 3.0, 3), (1, 10.0, 1), (1, None, 2), (2, None, 0)], "k int, v double, rep int").createOrReplaceTempView("reps")
    got = {r.k: r.m for r in spark.sql("SELECT k, median_of_means(v, rep, 3) AS m FROM reps GROUP BY k").collect()}
    assert got[1] == 6.0 and (got[2] is None or math.isnan(got[2]))


@pytest.mark.parametrize("shape,size,edges", [("star", 0, 0), ("star", 1, 0), ("star", 9, 8), ("complete", 6, 15), ("cycle", 2, 0), ("cycle", 5, 5), ("attached", 40, 39)])
def test_shapes(spark, shape, size, edges):
    from nodeflux.sources import synthetic

    synthetic.register(spark)
    rows = spark.read.format("shapes").option("shape", shape).option("size", size).option("parts", 3).load().collect()
    assert len(rows) == edges and len({frozenset(r) for r in rows}) == edges and all(0 <= v < size for r in rows for v in r)


def test_resident_graph_comes_in_parts(spark, purchase, monkeypatch):
    """The driver takes the graph a part at a time, and the truth comes from a task and not from rows of the driver."""
    from dataclasses import replace

    rows = sorted((r.src, r.pos, r.dst) for r in purchase.edges.collect())
    known = resident.power(resident.csr(purchase), P, 20)

    def refuse(*_, **__):
        raise AssertionError("rows of the graph on the driver")

    for name in ("toPandas", "collect"):
        monkeypatch.setattr(type(purchase.edges), name, refuse)
    monkeypatch.setattr(resident, "PART_ROWS", 700)
    fresh = replace(purchase)
    c = resident.csr(fresh)
    monkeypatch.setattr(type(spark), "createDataFrame", refuse)
    truth = workloads.truth(fresh, P, 20)
    monkeypatch.undo()
    assert c.nbr.tolist() == [dst for _, _, dst in rows] and np.array_equal(np.diff(c.ptr), np.bincount([src for src, _, _ in rows]))
    assert [r.pi for r in truth.orderBy("node").collect()] == known.tolist()


def test_resident_graph_passes_by_the_driver(spark, monkeypatch):
    """Neither broadcast nor fetched in parts: the arrays are dealt to the tasks, and a node without edges is kept."""
    g = make(spark, star(40) + [(i, i + 1) for i in range(1, 40)], isolated=(990,))
    asked = targets(spark, 0, 7, 99)  # hub, another, unknown

    def refuse(*_, **__):
        raise AssertionError("the graph on the driver")

    for name in ("toLocalIterator", "toPandas", "collect"):
        monkeypatch.setattr(type(g.edges), name, refuse)
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", refuse)
    monkeypatch.setattr(resident, "PART_ROWS", 16)
    rows, pi = resident.resident(g, workloads.jobs(asked, workloads.METHODS), P.but(c=0.5)), resident.power_rows(g, P, 20)
    monkeypatch.undo()
    got, truth = sorted(rows.collect(), key=lambda r: (r.qid, r.method)), [r.pi for r in pi.orderBy("node").collect()]
    c = resident.csr(g)
    assert c.n == 42 and c.deg.tolist() == [r.deg for r in g.nodes.orderBy("node").collect()] and truth == resident.power(c, P, 20).tolist()
    import pandas as pd

    plain = pd.DataFrame([(q, 0, t, m) for q, t in enumerate((0, 7, 99)) for m in workloads.METHODS], columns=["qid", "rep", "t", "method"])
    known = sorted(resident.solve(c, plain, P.but(c=0.5), {}), key=lambda r: (r[0], r[9]))
    assert len(got) == 2 * len(workloads.METHODS) and [(*r[:8], r[9]) for r in got] == [(*r[:8], r[9]) for r in known]


def test_targets_share_one_run_of_whole_graph_methods(tree, monkeypatch):
    import pandas as pd

    calls, own = [], resident.walk_counts
    monkeypatch.setattr(resident, "walk_counts", lambda *a: calls.append(a) or own(*a))
    jobs = pd.DataFrame([(q, rep, 2 * q, "walk_sample") for q in range(4) for rep in range(2)], columns=["qid", "rep", "t", "method"])
    c = resident.csr(tree)
    rows = resident.solve(c, jobs, P, {"n_walks": 3000})
    assert len(rows) == 8 and len(calls) == 2
    assert all(r[3] == own(c, 3000, P, r[1])[r[2]] / 3000 for r in rows)


def test_cost_of_a_run_whose_stages_are_dropped(tmp_path):
    """A session that keeps five stages: skipped stages are dropped first, and none that ran is missed."""
    import subprocess
    import sys

    code = f"""
from pyspark.sql import SparkSession, functions as F
spark = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").config("spark.ui.retainedStages", 5).config("spark.ui.retainedJobs", 5).config("spark.sql.shuffle.partitions", 2).config("spark.sql.adaptive.enabled", "false").getOrCreate()
from nodeflux.plans.cost import spark_cost
spark.range(1000).write.parquet({str(tmp_path / "t")!r})
def run():
    rdd = spark.sparkContext.parallelize(range(100), 2).map(lambda x: (x % 7, x)).groupByKey(2)
    for _ in range(12):
        rdd.count()
        spark.read.parquet({str(tmp_path / "t")!r}).agg(F.sum("id")).write.format("noop").mode("overwrite").save()
        import time; time.sleep(0.5)
got = spark_cost(spark, run)
print("GOT", got.jobs, got.stages, got.rows_read)
"""
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, timeout=200)
    got = [line.split()[1:] for line in out.stdout.splitlines() if line.startswith("GOT")]
    assert got, out.stderr[-2000:]
    jobs, stages, rows = map(int, got[0])
    assert jobs >= 24 and rows >= 12_000 and stages >= 36


def test_neighbours_of_copies_and_of_missing_vectors(spark, tmp_path, monkeypatch):
    """Of equal scores the least ids count, whatever the blocks; a pair without a score comes last, as in SQL."""
    from nodeflux.sources import graphs

    rng_ = np.random.default_rng(4)
    one = rng_.normal(size=8)
    vectors = {i: rng_.normal(size=8) for i in range(4)} | {i: one for i in range(4, 30)}
    rows = [(i, [float(x) for x in v]) for i, v in vectors.items()] + [(-1, None), (40, [1.0] * 7 + [None])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    monkeypatch.setattr(graphs, "KNN_VECTORS", 7)
    got: dict[int, set] = {}
    for r in graphs.knn(spark, str(tmp_path)).collect():
        got.setdefault(int(r.a[2:]), set()).add(int(r.b[2:]))
    unit = {i: np.float32(v).astype(float) for i, v in vectors.items()}
    cos = lambda a, b: round(float(unit[a] @ unit[b] / np.linalg.norm(unit[a]) / np.linalg.norm(unit[b])), 9)
    for a in vectors:
        assert got[a] == set(sorted((b for b in vectors if b != a), key=lambda b: (-cos(a, b), b))[:5])
    assert got[-1] == {0, 1, 2, 3, 4} and got[40] == {-1, 0, 1, 2, 3}


@pytest.mark.parametrize("mode", ["complete", "append"])
def test_streams_end_in_a_written_table(spark, sf, mode):
    """No row of the result is held by the driver, and a stream over no file gives no row."""
    from nodeflux.streaming import activity as st

    events = st.read_events(spark, sf)
    got = st.collect_stream(st.sessions(events, "2 hours") if mode == "complete" else events.select("user_id", "event_id"), mode, f"written_{mode}")
    assert got.inputFiles() and (mode == "complete" or got.count() == 1000)
    none = st.collect_stream(spark.readStream.schema("a long").parquet("/root/testdata/sf0.001/no*.parquet").select("a"), mode, f"none_{mode}") if mode == "append" else None
    assert none is None or none.count() == 0


@pytest.mark.parametrize("shape,edges", [("star", 4), ("complete", 10), ("cycle", 5), ("attached", 4)])
def test_shapes_over_the_keys_of_a_table(spark, shape, edges):
    from nodeflux.sources import synthetic

    keys = spark.createDataFrame([(k,) for k in (70, -3, None, 9, 9, 12, 1000)], "key long")
    rows = sorted(map(tuple, synthetic.over(keys, shape, 7).collect()))
    synthetic.register(spark)
    assert len(rows) == edges and rows == sorted(map(tuple, spark.read.format("shapes").option("shape", shape).option("size", 5).option("seed", 7).load().collect()))


def test_statistics_build_no_graph(spark, sf, monkeypatch):
    from nodeflux.queries import QUERIES

    built = {name: graph.graph(spark, sf, name).stats for name in ("tree", "session")}
    monkeypatch.setattr(graph, "_built", {})
    monkeypatch.setattr(graph, "build", None)
    assert {name: graph.stats(spark, sf, name) for name in built} == built
    assert QUERIES["graph_stats"](spark, sf).count() == 14


def test_largest_first_pushes_keep_no_entry_a_neighbour(spark, sf):
    """The order and the sums of a plain heap, in memory that follows the nodes and not the pushes."""
    import heapq
    import tracemalloc

    c, eps = resident.csr(graph.graph(spark, sf, "supply")), 2e-4
    for t in (3, c.n - 2):
        reserve, residue, touched, heap = np.zeros(c.n), np.zeros(c.n), 0, [(-1.0, t)]
        residue[t] = 1.0
        while heap:
            r, v = heapq.heappop(heap)
            if -r != residue[v]:
                continue
            x, residue[v] = residue[v], 0.0
            reserve[v] += P.alpha * x
            around = c.nbr[c.ptr[v] : c.ptr[v + 1]]
            residue[around] += (1 - P.alpha) * x / c.deg[around]
            touched += len(around)
            for u in around[residue[around] >= eps].tolist():
                heapq.heappush(heap, (-residue[u], u))
        tracemalloc.start()
        got = resident.reverse_query(c, t, eps, P, True)
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert np.array_equal(got[0], reserve) and np.array_equal(got[1], residue) and got[2] == touched > 10 * c.n
        assert peak < 10 * 8 * c.n


@pytest.mark.parametrize("shared_bytes", [0, 1 << 25])
def test_whole_series_are_products_of_blocks(spark, purchase, monkeypatch, shared_bytes):
    """Several ranges and blocks, with vectors broadcast or not; no hop joins edges row by row."""
    from dataclasses import replace

    from nodeflux.operators import blocks

    def refuse(*_, **__):
        raise AssertionError("a hop by rows")

    c = resident.csr(purchase)
    for module, name in ((exact, "series"), (push, "next_residue")):
        monkeypatch.setattr(module, name, refuse)
    for name, value in (("WIDTH", 150), ("EDGES", 400), ("BROADCAST_BYTES", shared_bytes)):
        monkeypatch.setattr(blocks, name, value)
    g = replace(purchase)
    r, want = np.full(c.n, 1 / c.n), np.full(c.n, P.alpha / c.n)
    for _ in range(9):
        r = (1 - P.alpha) * np.bincount(c.nbr, weights=np.repeat(r / c.deg, c.deg), minlength=c.n)
        want += P.alpha * r
    got = {row.node: row.pi for row in exact.truncated_pagerank(g, P, 9).collect()}
    assert len(got) == c.n and np.allclose([got[v] for v in range(c.n)], want, rtol=1e-12)
    rows = adaptive_push(g, targets(spark, 3, c.n - 1, 3), P, theta=0.0, hops=9, sampler="edge").df.collect()
    assert len(rows) == 3 and blocks.blocks(g).count() > 4
    for x in rows:
        pi, increments, whole, draws = resident.push_query(c, x.t, 0.0, 9, P, "edge", 0, 0, 0)
        assert math.isclose(x.pagerank, pi, rel_tol=1e-12) and (x.increments, x.exact_increments, x.draws) == (increments, whole, draws)


def test_query_sets_run_graph_by_graph_and_give_memory_back(spark, sf, monkeypatch):
    """The answers of each graph are written on their own, and the driver's whole heap is collected while graphs are built."""
    def whole() -> int:
        beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
        return sum(b.getCollectionCount() for b in beans if any(x in b.getName() for x in ("Old", "MarkSweep")))

    before = whole()
    g = make(spark, star(9))
    assert g.stats.n == 10 and whole() > before
    monkeypatch.setattr(workloads, "graph", lambda *_: g)
    before = whole()
    rows = workloads.run_query_set(spark, sf, ["one", "two"], ("adaptive_push", "walk_sample"), "uniform", P.but(c=0.5), k=3)
    assert whole() >= before + 2
    assert "MapInArrow" not in rows._jdf.queryExecution().toString()
    known = {(r.qid, r.t, r.method): r.pagerank for r in workloads.answers(g, uniform_targets(g, 3), ("adaptive_push", "walk_sample"), P.but(c=0.5)).collect()}
    assert sorted((r.graph, r.qid, r.t, r.method, r.pagerank) for r in rows.collect()) == sorted((x, *k, v) for x in ("one", "two") for k, v in known.items())


def test_packed_lists_equal_joined_edges(spark, monkeypatch):
    """Lists of packed numbers give the nodes, edges and places that joins give: hubs over several ranges, duplicates, loops, nulls, a lone node."""
    from nodeflux.operators import lists

    pairs = star(300) + [(i, i + 1) for i in range(1, 200)] + [(7, 3), (3, 7), (5, 5), (7, 3)]
    raw = spark.createDataFrame([(f"x:{a:04d}", f"x:{b:04d}") for a, b in pairs] + [(None, "x:0001"), ("x:0009", None)], "a string, b string")
    lone = spark.createDataFrame([("x:9000",), ("x:0003",), (None,)], "key string")
    monkeypatch.setattr(lists, "RANGE_ROWS", 100)
    monkeypatch.setattr(lists, "CODE_ROWS", 64)
    packed = graph.build(raw, lone)
    assert isinstance(packed, graph.Listed) and len(packed.offsets) > 3
    drawn = sorted(map(tuple, packed.pairs.collect()))
    monkeypatch.setattr(graph, "PACKED_ROWS", 0)
    joined = graph.build(raw, lone)
    assert not isinstance(joined, graph.Listed) and packed.stats == joined.stats
    for name, columns in (("edges", ("src", "dst", "pos", "src_deg", "dst_deg")), ("nodes", ("node", "key", "kind", "deg"))):
        one, two = (sorted(map(tuple, getattr(g, name).select(*columns).collect())) for g in (packed, joined))
        assert one == two, name
    assert drawn == sorted(map(tuple, joined.edges.select("src", "dst").collect()))
    a, b = resident.csr(packed), resident.csr(joined)
    assert a.nbr.tolist() == b.nbr.tolist() and a.ptr.tolist() == b.ptr.tolist()


def test_walks_by_number_follow_the_law(tree, monkeypatch):
    """Walks that are kept as numbers, dealt or drawn one by one, end as often as PageRank says, and none is lost."""
    c = resident.csr(tree)
    truth, walks = resident.power(c, P, 100), 2_000_000
    for edge in (0, 16, 1 << 40):
        monkeypatch.setattr(resident, "DEAL_EDGE", edge)
        held = resident.walk_counts(c, walks, P, 3)
        z = (held - walks * truth) / np.sqrt(walks * truth * (1 - truth))
        assert held.sum() == walks and abs(z).max() < 6 and 0.7 < z.std() < 1.3


def test_shares_of_walks_add_up(tree, monkeypatch):
    """One sample of walks over several tasks: as many walks, and each target's value is theirs together."""
    monkeypatch.setattr(resident, "SHARE_WALKS", 10_000)
    asked = targets(tree.spark, 0, 3)
    rows = resident.resident(tree, workloads.jobs(asked, ("walk_sample", "power_iteration")), P, n_walks=40_003).collect()
    got = {(r.t, r.method): r for r in rows}
    c = resident.csr(tree)
    parts = [resident.walk_counts(c, 40_003 * (i + 1) // 4 - 40_003 * i // 4, P, [0, i]) for i in range(4)]
    assert len(rows) == 4 and all(got[t, "walk_sample"].increments == 40_003 for t in (0, 3))
    assert all(abs(got[t, "walk_sample"].pagerank - sum(x[t] for x in parts) / 40_003) < 1e-12 for t in (0, 3))


def test_kernels_in_pieces_equal_whole_ones(tree, monkeypatch):
    """Edges a few at a time, and sums over all nodes: the same pushes and values."""
    c = resident.csr(tree)
    calls = (
        lambda: resident.push_query(c, 2, 1e-4, 30, P, "edge", 1, 0, 0), lambda: resident.push_query(c, 2, 1e-3, 30, P, "skip", 1, 0, 0),
        lambda: resident.randomized_query(c, 2, 1e-5, 20, P, "shared", 1, 0, 0), lambda: resident.reverse_query(c, 2, 1e-5, P)[0].sum(),
    )
    whole = [np.array(f()) for f in calls]
    monkeypatch.setattr(resident, "SPREAD_EDGES", 5)
    assert all(np.allclose(f(), x, rtol=1e-9) for f, x in zip(calls, whole))


def test_graphs_of_a_gigabyte_are_resident():
    """Purchase and supply graphs of 36 million raw edges: the distributed plans of whole query sets do not end in time."""
    g = graph.Graph(None, None, graph.Stats(2_100_000, 36_000_000, 600))
    assert resident.fits(g) and g.stats.m <= graph.PACKED_ROWS
