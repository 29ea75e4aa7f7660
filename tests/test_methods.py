"""The methods against worked examples, closed forms and brute force."""

import math

import numpy as np
import pytest

from localcomm.operators import forecast as fc
from localcomm.operators import graph as gr
from localcomm.operators import metrics as me
from localcomm.operators import partition as pa
from localcomm.operators import ranking, walks
from localcomm.params import Params, derive_params
from localcomm.plans.experiments import toy


def rows(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


@pytest.fixture(scope="module")
def four(spark):
    nodes = spark.createDataFrame([(1, list("abc")), (2, list("abd")), (3, ["e"]), (4, list("abc"))], "node long, attrs array<string>")
    return nodes, gr.structure_graph(spark.createDataFrame([(1, 2), (2, 1), (3, 2), (3, 4), (4, 4), (None, 1)], "src long, dst long"))


def test_structure_graph_drops_loops_repeats_and_nulls(four):
    assert rows(four[1], "src", "dst") == [(1, 2), (2, 3), (3, 4)]


@pytest.mark.parametrize(("t_e", "new"), [(0.7, [(1, 4, 1.0)]), (0.5, [(1, 4, 1.0)]), (0.4, [(1, 4, 1.0), (2, 4, 0.5)]), (1.0, [])])
def test_three_graphs(four, t_e, new):
    nodes, edges = four
    b = gr.combined_graph(gr.attribute_graph(nodes, edges, t_e=t_e))
    assert rows(b, "src", "dst", "w") == sorted([(1, 2, 1.5), (2, 3, 1.05), (3, 4, 1.05), *new])


def test_toy_ratio_cut(spark):
    nodes, edges = toy(spark)
    c = gr.combined_graph(gr.attribute_graph(nodes, edges))
    members = spark.createDataFrame([(1, n) for n in (1, 2, 3, 4)], "seed long, node long")
    r = me.ratio_conductance(members, c).first()
    assert (round(r["cut"], 6), round(r["vol"], 6), round(r["score"], 6)) == (0.977273, 12.0, 0.081439)
    assert round(me.classic_conductance(members, gr.plain_graph(edges)).first()["score"], 6) == 0.2
    q = me.partition_quality(members, edges).first()
    assert (q["edges"], round(q["density"], 6), q["triangles"]) == (4, 0.666667, 0)


def test_sweep_windows_equal_the_definition(spark):
    nodes, edges = toy(spark)
    c = gr.combined_graph(gr.attribute_graph(nodes, edges))
    order = spark.createDataFrame([(1, i, i, 1.0, 1.0) for i in (1, 2, 3, 4)], "seed long, position int, node long, rank double, share double")
    from pyspark.sql import functions as F

    sub = c.select(F.lit(1).cast("long").alias("seed"), "src", "dst", "w")
    got = rows(ranking.sweep_curve(order, sub, gr.degrees(c, "w"), Params(), 26.7), "position", "orphans", "score")
    assert got[0] == (1, 1, None)
    assert [round(s, 6) for _, _, s in got[1:]] == [0.613398, 0.460578, 0.081439]


def test_rank_of_two_vertices():
    src, dst, w = np.array([0, 1]), np.array([1, 0]), np.ones(2)
    q, _, _ = ranking.rank_vector(src, dst, w, 2, 0, Params(stop="fixed"), derive_params(1, Params(eps=0.0)))
    assert np.allclose(q, [0.6, 0.4])


def test_derived_parameters():
    a, b = derive_params(8690, Params(phi_o=0.2)), derive_params(4_258_946, Params(phi_o=0.05))
    assert (a.l, a.t_last, b.l, b.t_last) == (14, 9465, 23, 310_080)
    assert math.isclose(a.eps, 2.783e-11, rel_tol=1e-3) and math.isclose(b.eps, 2.456e-14, rel_tol=1e-3)


@pytest.mark.parametrize(("edges", "want"), [([(1, 2)], {2: 0.85}), ([(1, 2), (2, 3)], {2: 0.85, 3: 0.565558})])
def test_hit_probabilities(spark, edges, want):
    g = gr.plain_graph(spark.createDataFrame(edges, "src long, dst long"))
    seeds = spark.createDataFrame([(1,)], "seed long")
    n = 10_000
    hits = {r["node"]: r["hits"] for r in walks.walk_visits(g, seeds, Params(n_w=n)).collect()}
    assert hits[1] == n
    for node, h in want.items():
        assert abs(hits[node] - n * h) < 4 * math.sqrt(n * h * (1 - h))


def test_walk_engines_agree(spark):
    g = gr.plain_graph(spark.createDataFrame([(1, 2), (2, 3), (3, 1), (3, 4)], "src long, dst long"))
    seeds = spark.createDataFrame([(1,), (4,), (None,)], "seed long")
    for mode in ("until_restart", "fixed_length"):
        p = Params(n_w=200, max_hops=5, walk_mode=mode)
        a, b = (rows(walks.walk_visits(g, seeds, p.but(engine=e)), "seed", "node", "hits") for e in ("local", "relational"))
        assert a == b and a


@pytest.mark.parametrize("p", [Params(), Params(stop="mass"), Params(stop="fixed", eps_t=0.3), Params(eps=1e-2), Params(eps=1e-2, truncate="output", stop="mass"), Params(cut_scope="subgraph"), Params(measure="classic", cut_scope="subgraph", eps_t=0.1)])
@pytest.mark.parametrize("whole", [True, False])
def test_rank_engines_agree(spark, p, whole):
    nodes, edges = toy(spark)
    c = gr.combined_graph(gr.attribute_graph(nodes, edges))
    seeds = spark.createDataFrame([(1,), (8,), (77,)], "seed long")
    p, out = p.but(n_w=300), []
    for e in ("local", "relational"):
        if whole:
            out.append(pa.attributed_partition(c, seeds, 10, p.but(engine=e), use_proximity=False))
        else:  # two subgraphs, one of them a part
            sub = gr.induced(c, spark.createDataFrame([(1, n) for n in range(1, 11)] + [(8, n) for n in range(4, 11)], "seed long, node long")).select("seed", "src", "dst", "w")
            out.append(pa.ranked_and_swept(sub, None, gr.degrees(c, "w"), seeds, p.but(engine=e), derive_params(12, p), 26.7))
    a, b = (rows(r.curve, "seed", "position", "node", "rank", "cut", "vol", "score") for r in out)
    assert [x[:3] for x in a] == [x[:3] for x in b] and a
    for x, y in zip(a, b, strict=True):
        assert all((u is None) == (v is None) and (u is None or abs(u - v) < 1e-9) for u, v in zip(x[3:], y[3:], strict=True))
    assert rows(out[0].summary, "seed", "size", "target_met") == rows(out[1].summary, "seed", "size", "target_met")


def test_truncation_and_stops_change_ranks(spark):
    """The variants above are no idle switches: they give other ranks on the toy graph."""
    nodes, edges = toy(spark)
    c = gr.combined_graph(gr.attribute_graph(nodes, edges))
    seeds = spark.createDataFrame([(1,)], "seed long")
    seen = {tuple(x[1] for x in rows(pa.attributed_partition(c, seeds, 10, p, use_proximity=False).curve, "node", "rank")) for p in (Params(), Params(stop="fixed"), Params(eps=1e-2), Params(eps=1e-2, truncate="output"), Params(eps_t=0.1))}
    assert len(seen) == 5


def test_forecast_engines_and_second_walk(spark):
    nodes, edges = toy(spark)
    c, seeds = gr.combined_graph(gr.attribute_graph(nodes, edges)), spark.createDataFrame([(1,), (5,)], "seed long")
    p = Params(n_w=400, t_e=0.2, t_s=5.0)
    a, b = (rows(fc.forecast_community(c, nodes, seeds, 10, p.but(engine=e)).summary, "seed", "size", "target_met") for e in ("local", "relational"))
    assert a == b and len(a) == 2
    once, twice = (fc.forecast_community(c, nodes, seeds, 10, p, rewalk=r).sub_edges for r in (False, True))
    kept = set(rows(twice, "seed", "src", "dst"))
    assert kept <= set(rows(once, "seed", "src", "dst")) and kept


def test_push_matches_a_direct_solve(spark):
    e = [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5)]
    got = {r["node"]: (r["rank"], r["residual"]) for r in ranking.push_rank(gr.plain_graph(spark.createDataFrame(e, "src long, dst long")), spark.createDataFrame([(1,)], "seed long"), eps=1e-7).collect()}
    a = np.zeros((5, 5))
    for x, y in e:
        a[x - 1, y - 1] = a[y - 1, x - 1] = 1
    lazy = 0.5 * (np.eye(5) + a / a.sum(1, keepdims=True))
    want = 0.2 * np.linalg.inv(np.eye(5) - 0.8 * lazy)[0]
    assert np.allclose([got[n][0] for n in range(1, 6)], want, atol=1e-5)
    assert all(got[n][1] <= 1e-7 * a.sum(1)[n - 1] for n in got)
    with pytest.raises(RuntimeError):
        ranking.push_rank(gr.plain_graph(spark.createDataFrame(e, "src long, dst long")), spark.createDataFrame([(1,)], "seed long"), eps=1e-7, rounds=2)


def test_ratio_components_add_up(spark):
    nodes, edges = toy(spark)
    c = gr.combined_graph(gr.attribute_graph(nodes, edges))
    got = {r["node"]: r for r in me.ratio_components(spark.createDataFrame([(1, n) for n in (1, 2, 3, 4)], "seed long, node long"), c).collect()}
    for n, r in got.items():
        own = [x for x in c.collect() if n in (x["src"], x["dst"])]
        inside = [x for x in own if {x["src"], x["dst"]} <= {1, 2, 3, 4}]
        assert (r["int_g"], r["ext_g"]) == (len(inside), len(own) - len(inside))
        assert math.isclose(r["int_a"], sum(x["w_a"] for x in inside)) and math.isclose(r["int_a"] + r["ext_a"], sum(x["w_a"] for x in own))


def test_gain_counts_vertices_and_edges(spark):
    m = lambda xs: spark.createDataFrame([(1, x) for x in xs], "seed long, node long")
    e = lambda xs: spark.createDataFrame([(1, *x) for x in xs], "seed long, src long, dst long")
    g = me.forecast_gain(m([1, 2, 3]), m([1, 9]), m([1, 2]), e([(1, 2), (2, 3)]), e([(1, 9)]), e([(1, 2)])).first()
    assert (g["dv_removed"], g["dv_forecast"], g["gain_v"], g["gain_e"]) == (3, 1, 2, 2)


def test_grids_in_one_job_equal_single_runs(spark):
    from localcomm.plans import experiments as ex
    from localcomm.sources import Graph

    nodes, edges = toy(spark)
    w = type("W", (), {})()
    w.nodes, w.edges, w.n, w.combined = nodes, edges, 10, Graph(nodes, edges).combined()
    w.seeds = lambda k: gr.sample_seeds(edges, k)
    p = Params(stop="fixed", n_w=200)
    grid = (("alpha_r", 0.3), ("alpha_n", 0.5), ("t_s", 5.0))
    got = {(r["parameter"], r["value"]): (r["partition_difference"], r["top20_difference"]) for r in ex.subgraph_accuracy(w, grid, 3, p).collect()}
    for name, value in grid:
        q = p.but(**{name: value})
        a, b = (pa.attributed_partition(w.combined, w.seeds(3), 10, q, use_proximity=u) for u in (True, False))
        mean = lambda df, c: float(np.mean([r[c] for r in df.collect()]))
        assert got[name, value] == (mean(me.set_difference_size(a.members, b.members), "symmetric"), mean(me.topk_difference(a.curve, b.curve), "difference"))
    gains = {r["value"]: (r["gain_v"], r["gain_e"]) for r in ex.forecast_sweep(w, "t_e", (0.1, 0.5), 3, p.but(t_s=5.0)).collect()}
    less = Graph(nodes, gr.drop_edges(edges, 0.15)).combined()
    for t_e in (0.1, 0.5):
        q = p.but(t_s=5.0, t_e=t_e)
        a, b, c = pa.attributed_partition(w.combined, w.seeds(3), 10, q), pa.attributed_partition(less, w.seeds(3), 10, q), fc.forecast_community(less, nodes, w.seeds(3), 10, q)
        x = me.set_difference_size(a.members, b.members).toPandas().set_index("seed")["symmetric"] - me.set_difference_size(a.members, c.members).toPandas().set_index("seed")["symmetric"]
        assert gains[t_e][0] == float(x.mean())


@pytest.mark.parametrize("p", [Params(n_w=500), Params(n_w=500, rule="count", min_hits=40, measure="classic"), Params(n_w=300, walk_mode="fixed_length", max_hops=6, weighted=False)])
def test_one_task_a_seed_equals_the_steps(spark, p):
    rng = np.random.default_rng(5)
    pairs = {(int(min(a, b)), int(max(a, b))) for a, b in rng.integers(0, 40, (120, 2)) if a != b}
    nodes = spark.createDataFrame([(i, [f"v{k}" for k in rng.integers(0, 9, 4)]) for i in range(42)], "node long, attrs array<string>")
    c = gr.combined_graph(gr.attribute_graph(nodes, spark.createDataFrame(sorted(pairs), "src long, dst long")))
    seeds = spark.createDataFrame([(1,), (7,), (41,), (None,)], "seed long").where("seed IS NOT NULL")
    a, b = (pa.attributed_partition(c, seeds, 42, p.but(engine=e)) for e in ("auto", "relational"))
    assert a.sub_edges is None and b.sub_edges is not None
    assert rows(a.members, "seed", "node", "position") == rows(b.members, "seed", "node", "position")
    assert rows(a.summary, "seed", "size", "target_met") == rows(b.summary, "seed", "size", "target_met")


def test_isolated_seed_is_alone(spark):
    c = gr.plain_graph(spark.createDataFrame([(1, 2)], "src long, dst long"))
    r = pa.attributed_partition(c, spark.createDataFrame([(9,)], "seed long"), 3, Params(n_w=50))
    assert rows(r.members, "seed", "node") == [(9, 9)] and r.summary.first()["score"] is None


def test_completion_strategies_agree(spark):
    nodes = spark.createDataFrame([(i, [f"a{(i * k) % 7}" for k in range(1, 5)] + [f"b{i % 3}"]) for i in range(40)] + [(99, None), (98, [])], "node long, attrs array<string>")
    for t in (0.3, 0.6, 0.8):
        a, b = (rows(fc.similar_pairs(nodes, t, s), "src", "dst") for s in ("pairs", "prefix"))
        assert a == b
        found = set(rows(fc.similar_pairs(nodes, t, "minhash"), "src", "dst"))
        assert found <= set(a) and len(found) >= 0.9 * len(a)


def test_planted_blocks(spark):
    rng = np.random.default_rng(3)
    pairs = [(i, j) for i in range(100) for j in range(i) if rng.random() < (0.4 if i // 25 == j // 25 else 0.02)]
    nodes = spark.createDataFrame([(i, [f"v{i // 25}-{k}" for k in rng.choice(10, 8, replace=False)]) for i in range(100)], "node long, attrs array<string>")
    c = gr.combined_graph(gr.attribute_graph(nodes, gr.structure_graph(spark.createDataFrame([(int(a), int(b)) for a, b in pairs], "src long, dst long"))))
    r = pa.attributed_partition(c, spark.createDataFrame([(5,), (60,)], "seed long"), 100, Params(n_w=2000, stop="fixed"))
    for seed in (5, 60):
        got = [n for s, n in rows(r.members, "seed", "node") if s == seed]
        assert sum(n // 25 == seed // 25 for n in got) >= 0.8 * len(got)


def test_set_measures(spark):
    m = lambda xs: spark.createDataFrame([(1, x) for x in xs], "seed long, node long")
    d = me.set_difference_size(m([1, 2, 3]), m([2, 3, 4, 5])).first()
    assert (d["symmetric"], d["only_a"], d["only_b"]) == (3, 1, 2)
    k4 = spark.createDataFrame([(a, b) for a in range(4) for b in range(a + 1, 4)], "src long, dst long")
    q = me.partition_quality(m(range(4)), k4).first()
    assert (q["triangles"], q["triangles_x3"], q["density"]) == (4, 12, 1.0)
    assert me.partition_quality(m([1]), k4).first()["density"] is None


def test_components_and_stats(spark):
    nodes = spark.createDataFrame([(i, ["x"]) for i in range(8)], "node long, attrs array<string>")
    r = gr.network_stats(nodes, spark.createDataFrame([(0, 1), (1, 2), (2, 3), (5, 6)], "src long, dst long")).first()
    assert (r["n"], r["m"], r["isolated"], r["components"], r["largest"]) == (8, 4, 2, 4, 4)


def test_removing_nothing_gains_nothing(spark):
    e = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    assert gr.drop_edges(e, 0.0).count() == 2 and gr.edge_fraction(e, 10).count() == 2


def test_truncated_walk_is_not_cut(spark):
    # Two cliques at the ends of a long path: rank needs far more than 40 steps to get across.
    pairs = [(o + i, o + j) for o in (0, 100) for i in range(6) for j in range(i)] + [(k, k + 1) for k in range(5, 60)] + [(60, 100)]
    e = gr.structure_graph(spark.createDataFrame(pairs, "src long, dst long"))
    r = pa.truncated_walk_partition(e, spark.createDataFrame([(2,)], "seed long"), 67, Params(stop="fixed", phi_o=0.5))
    nodes = sorted({x for p in pairs for x in p})
    at, d = {v: i for i, v in enumerate(nodes)}, derive_params(len(pairs), Params(phi_o=0.5))
    a = np.zeros((len(nodes), len(nodes)))
    for x, y in pairs:
        a[at[x], at[y]] = a[at[y], at[x]] = 1
    deg, q = a.sum(1), np.eye(len(nodes))[at[2]]
    for _ in range(d.t_last):
        q = 0.5 * (q + a @ (q / deg))
        q[q <= d.eps * deg] = 0
    got = {x["node"]: x["rank"] for x in r.curve.collect()}
    assert set(got) == {v for v in nodes if q[at[v]] > 0} and 100 in got
    assert np.allclose([got[v] for v in sorted(got)], [q[at[v]] for v in sorted(got)], rtol=1e-9, atol=0)


def test_experiments_are_registered_whole(monkeypatch):
    import inspect

    from localcomm.plans import catalogue as cat
    from localcomm.plans import experiments as ex

    calls = {}
    monkeypatch.setattr(cat, "world", lambda s, d, name="parts": name)
    monkeypatch.setattr(ex, "parts_before", lambda s, d: None)
    for f in ("subgraph_accuracy", "trial_insensitivity", "size_independence", "effectiveness", "forecast_sweep", "rank_times", "scalability", "seed_latency"):
        sig = inspect.signature(getattr(ex, f))

        def note(*a, f=f, sig=sig, **k):
            bound = sig.bind(*a, **k)
            bound.apply_defaults()
            calls.setdefault(f, []).append(bound.arguments)

        monkeypatch.setattr(ex, f, note)
    for name, run in cat.QUERIES.items():
        if name.startswith("experiment_") and "walk_counts" not in name:
            run(None, "")
    assert all(c["p"].n_w == 10_000 and c["p"].max_hops == 50 for cs in calls.values() for c in cs)
    assert len(calls) == 8 and all(len(c["grid"]) == 31 and c["k"] == 10 for c in calls["subgraph_accuracy"])
    assert [len(c["trials"]) for c in calls["trial_insensitivity"]] == [7] and calls["trial_insensitivity"][0]["k"] == 10
    assert [list(c["tenths"]) for c in calls["size_independence"] + calls["scalability"]] == [list(range(1, 11))] * 2
    assert {(c["w"], c["k"], c["p"].phi_o) for c in calls["effectiveness"]} == {("parts", 20, 0.05), ("pages", 20, 0.05), ("docs", 100, 0.05)}
    assert {(c["w"], c["name"], len(c["values"]), c["k"]) for c in calls["forecast_sweep"]} == {(g, n, v, 20) for g in ("parts", "docs") for n, v in (("t_e", 9), ("phi_o", 6))}


def test_similar_pairs_meet_by_several_members_and_equal_sets_once(spark):
    """Sets of a few frequent members, many of them equal: candidates are pairs of distinct sets that come near the threshold."""
    import itertools

    rng = np.random.default_rng(3)
    sets = [sorted({f"b{rng.integers(5)}", f"t{rng.integers(3)}", f"s{rng.integers(3)}", *[f"w{v}" for v in rng.integers(6, size=rng.integers(1, 4))]}) for _ in range(120)] * 3
    nodes = spark.createDataFrame(list(enumerate(sets)), "node long, attrs array<string>")
    for t in (0.3, 0.5, 0.7, 1.0):
        want = sorted((i, j) for (i, a), (j, b) in itertools.combinations(enumerate(sets), 2) if len(set(a) & set(b)) > t * len(set(a) | set(b)))
        assert rows(fc.similar_pairs(nodes, t), "src", "dst") == want
        found = rows(fc.similar_pairs(nodes, t, "minhash"), "src", "dst") if t < 1 else want
        assert set(found) <= set(want) and len(found) >= 0.99 * len(want)
    distinct = spark.createDataFrame(list(enumerate(sorted(set(map(tuple, sets))))), "node long, x array<string>")
    near = {(r["src"], r["dst"]) for r in fc._prefix_pairs(distinct, 0.5, ()).collect()}
    lists = [set(r["x"]) for r in distinct.orderBy("node").collect()]
    exact = {(i, j) for i, j in itertools.combinations(range(len(lists)), 2) if len(lists[i] & lists[j]) >= 0.5 * len(lists[i] | lists[j])}
    assert exact <= near and len(near) <= 1.2 * len(exact)  # one member to a key gave nearly all pairs


def test_members_of_the_same_groups_meet_as_one(spark, monkeypatch):
    import itertools

    held = [(m, g) for m in range(60) for g in range(12) if (m % 15 * 7 + g * g) % 4 == 0] + [(None, 1), (99, 77), (100, 5)]
    df = spark.createDataFrame(held, "m long, g long")
    of = {}
    for m, g in held:
        of.setdefault(m, set()).add(g)
    want = sorted((a, b, len(of[a] & of[b])) for a, b in itertools.combinations(sorted(x for x in of if x is not None), 2) if of[a] & of[b])
    cols = ("src", "dst", "support")
    plain, calls = rows(gr.project_bipartite(df, "m", "g"), *cols), []
    real = gr._projected_classes
    monkeypatch.setattr(gr, "DENSE", 1)
    monkeypatch.setattr(gr, "_projected_classes", lambda *a: calls.append(1) or real(*a))
    assert rows(gr.project_bipartite(df, "m", "g"), *cols) == plain == want and calls
    assert rows(gr.project_bipartite(df, "m", "g", min_support=2), *cols) == [r for r in want if r[2] > 1]
    assert rows(gr.project_bipartite(df, "m", "g", max_group=20), *cols) == rows(gr._met(df.where("m IS NOT NULL"), df.where("m IS NOT NULL").groupBy("g").count().where("count BETWEEN 2 AND 20").withColumnRenamed("count", "size")), *cols)


def test_components_by_stars_are_those_of_spreading_labels(spark, monkeypatch):
    rng = np.random.default_rng(5)
    pairs = [tuple(map(int, p)) for p in rng.integers(400, size=(260, 2))] + [(i, i + 1) for i in range(1000, 1100)]  # many small ones, and a path
    edges = gr.structure_graph(spark.createDataFrame(pairs, "src long, dst long").repartition(5))
    nodes = spark.createDataFrame([(i,) for i in [*range(400), *range(1000, 1101), 5000]], "node long")
    want = rows(gr._spread_labels(nodes, edges), "node", "label")
    monkeypatch.setattr(gr, "_spread_labels", None)  # not needed while one task can end it
    assert rows(gr.component_labels(nodes, edges), "node", "label") == want
    monkeypatch.undo()
    monkeypatch.setattr(gr, "LABEL_ROWS", 10)
    assert rows(gr.component_labels(nodes, edges), "node", "label") == want


def test_a_graph_is_combined_only_when_needed(spark, monkeypatch):
    from localcomm import sources
    from localcomm.plans import catalogue as cat

    monkeypatch.setattr(sources.Graph, "combined", None)
    assert cat.QUERIES["structure_graph_users"](spark, "/root/testdata/sf0.001").count() == cat.world(spark, "/root/testdata/sf0.001", "users").edges.count()
