"""Graphs mapped from the shared folder against graphs sent to the tasks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from localcomm import sources
from localcomm.operators import graph as gr
from localcomm.operators import mapped, ranking, walks
from localcomm.operators import partition as pa
from localcomm.params import Derived, Params, derive_params
from localcomm.plans.stages import staged

P = Params(stop="fixed", n_w=500)


def rows(df, *cols):
    return sorted(tuple(round(v, 9) if isinstance(v, float) else v for v in (r[c] for c in cols)) for r in df.collect())


@pytest.fixture(scope="module")
def parts(spark):
    g = sources.parts(spark, "/root/testdata/sf0.001")
    nodes, edges = staged(g.nodes, "nodes"), staged(g.edges, "edges")
    combined = staged(sources.Graph(nodes, edges).combined(), "combined")
    seeds = gr.sample_seeds(edges, 4).union(spark.createDataFrame([(10**9,)], "seed long"))  # the last has no edges
    return edges, combined, staged(seeds, "seeds"), nodes.count()


def test_partitions_of_a_mapped_graph_are_those_of_a_sent_one(parts, monkeypatch):
    edges, combined, seeds, n = parts
    runs = {
        "attributed": lambda: pa.attributed_partition(combined, seeds, n, P).curve,
        "whole": lambda: pa.attributed_partition(combined, seeds, n, P, use_proximity=False).curve,
        "structural": lambda: pa.structural_partition(edges, seeds, n, P).curve,
    }
    cols = ("seed", "position", "node", "rank", "cut", "vol", "orphans", "score")
    sent = {k: rows(f(), *cols) for k, f in runs.items()}
    sent_visits = rows(walks.walk_visits(combined, seeds, P), "seed", "node", "hits")
    monkeypatch.setattr(mapped, "MAP_FROM", 0)
    monkeypatch.setattr(mapped, "PART_ROWS", 100)  # many parts
    monkeypatch.setattr(ranking, "whole_curves", None)  # nothing may be sent
    monkeypatch.setattr(pa, "fused_curves", None)
    assert {k: rows(f(), *cols) for k, f in runs.items()} == sent and all(sent.values())
    assert rows(walks.walk_visits(combined, seeds, P), "seed", "node", "hits") == sent_visits
    fixed = P.but(walk_mode="fixed_length", max_hops=5)
    assert rows(walks.walk_visits(combined, seeds, fixed), "seed", "node", "hits") == rows(walks.walk_visits(combined, seeds, fixed.but(engine="local")), "seed", "node", "hits")


def test_steps_over_all_rows_rank_as_a_component_does(parts, monkeypatch):
    _, combined, seeds, _ = parts
    g, d = mapped.opened(mapped.layout(combined)), derive_params(combined.count(), P)
    for seed in [r["seed"] for r in seeds.collect()][:3]:
        for p in (P, P.but(measure="classic"), P.but(cut_scope="subgraph"), P.but(stop="l1")):
            with monkeypatch.context() as m:
                own = g.compact(np.arange(g.n)).curve(seed, seed, p, d, 1e4)
                m.setattr(mapped, "OWN_ROWS", 0)
                m.setattr(mapped, "STEP_ROWS", 50)
                far = g.curve(seed, seed, p, d, 1e4)
            assert own["node"].tolist() == far["node"].tolist()
            np.testing.assert_allclose(own["score"].to_numpy(float), far["score"].to_numpy(float), atol=1e-9)


def test_ranks_that_come_round_are_those_of_all_steps():
    # Ranks that move on by one vertex of seven a step: after many steps they lie where whole rounds leave them.
    taken = []

    def arriving(q):
        taken.append(1)
        return 2 * np.roll(q, 1) - q

    p = Params(stop="fixed", alpha_n=0.0, truncate="output")
    q, steps = ranking.ranked(arriving, np.ones(7), 2, p, Derived(1, 10**6, 1.0, 0.0, 10**6))
    assert steps == 10**6 and np.flatnonzero(q).tolist() == [(2 + 10**6) % 7] and len(taken) < 50


def test_a_walk_that_has_settled_is_the_one_of_all_steps():
    # A path of 12 vertices: shares even out long before 20,000 steps.
    src = np.concatenate([np.arange(11), np.arange(1, 12)])
    dst = np.concatenate([np.arange(1, 12), np.arange(11)])
    deg, taken = np.bincount(src).astype(float), []

    def arriving(q):
        taken.append(1)
        return np.bincount(dst, weights=q[src] / deg[src], minlength=12)

    d = Derived(1, 20_000, 1.0, 1e-9, 20_000)
    p = Params(stop="fixed", alpha_n=0.0, truncate="feedback", measure="classic")
    q, steps = ranking.ranked(arriving, deg, 3, p, d)
    by_hand = np.zeros(12)
    by_hand[3] = 1.0
    for _ in range(20_000):
        by_hand = 0.5 * (by_hand + arriving(by_hand))
        by_hand[by_hand <= d.eps * deg] = 0.0
    assert steps == 20_000 and len(taken) - 20_000 < 2500
    np.testing.assert_array_equal(np.round(q / deg, ranking.DIGITS), np.round(by_hand / deg, ranking.DIGITS))
    # A walk that has not filled its component isn't settled, though its shares are alike.
    assert ranking.settled(np.array([1.0, 0.0]), np.array([0.5, 0.5]), np.ones(2), d) is None


def test_steps_in_threads_are_those_of_one(parts, monkeypatch):
    _, combined, seeds, _ = parts
    g, d = mapped.MappedGraph(mapped.layout(combined)), derive_params(combined.count(), P)
    monkeypatch.setattr(mapped, "OWN_ROWS", 0)
    monkeypatch.setattr(mapped, "STEP_ROWS", 50)
    seed = seeds.first()["seed"]
    assert g.curve(seed, seed, P, d, 1e4).equals(g.curve(seed, seed, P, d, 1e4, threads=3)) and len(g.spans) > 10


def arrays(where):
    g = mapped.MappedGraph(where)
    return {k: getattr(g, k).tolist() for k in ("node", "end", "deg", "dst", "w")}, g.moves(np.arange(g.n), np.arange(g.n) * 987_654_321 % 2_147_483_647).tolist()


def test_parts_and_twins_of_a_mapped_graph_are_those_written_anew(parts, monkeypatch):
    edges, combined, _, _ = parts
    monkeypatch.setattr(mapped, "PART_ROWS", 100)
    plain, anew = gr.plain_graph(edges), gr.plain_graph(edges)
    mapped.layout(combined)
    mapped.twins(plain, combined)
    assert mapped.layout(plain).folder == mapped.layout(combined).folder
    assert arrays(mapped.layout(plain)) == arrays(mapped.layout(anew))
    for t in (3, 10):
        part, again = (gr.edge_fraction(combined, t) for _ in range(2))
        mapped.kept(part, combined, gr.fraction_mask(t))
        assert arrays(mapped.layout(part)) == arrays(mapped.layout(again)) and mapped.layout(part).rows == 2 * part.count() > 0
    with pytest.raises(ValueError):
        mapped.kept(gr.edge_fraction(combined, 3), combined, gr.fraction_mask(4))


def test_grids_and_sizes_on_mapped_graphs_are_those_on_sent_ones(spark, monkeypatch):
    from localcomm.plans import catalogue as cat
    from localcomm.plans import experiments as ex

    w = cat.World(spark, "/root/testdata/sf0.001", "parts")
    grid = [("alpha_r", 0.3), ("t_s", 4.0), ("phi_o", 0.4)]
    runs = {
        "accuracy": lambda: rows(ex.subgraph_accuracy(w, grid, 3, P), "parameter", "value", "partition_difference", "top20_difference", "p"),
        "sizes": lambda: rows(ex.size_independence(w, (4, 10), 3, P), "tenth", "m", "p", "m_p"),
        "trials": lambda: rows(ex.trial_insensitivity(w, (50, 200), 3, P), "n_w", "p"),
    }
    sent = {k: f() for k, f in runs.items()}
    monkeypatch.setattr(mapped, "MAP_FROM", 0)
    monkeypatch.setattr(gr, "adjacency", None)  # no table of transitions for a graph that is mapped
    assert {k: f() for k, f in runs.items()} == sent
    times = ex.scalability(w, (4, 10), 2, P).collect()
    assert [r["tenth"] for r in times] == [4, 10] and times[1]["m"] == w.edges.count()


def test_seeds_are_dealt_over_tasks(parts, spark):
    edges, combined, _, n = parts
    many = staged(gr.sample_seeds(edges, 60), "many")
    m, total = combined.count(), 1e4
    curves = pa.fused_curves(combined, gr.degrees(combined, "w"), many, n, P, derive_params(m, P), total)
    tasks = curves.select("seed", F.spark_partition_id().alias("t")).agg(F.countDistinct("t"), F.countDistinct("seed")).first()
    assert tasks[0] > 4 and tasks[1] == 60
    assert curves.rdd.getNumPartitions() > 4


def test_small_groups_meet_in_lists_as_in_joins(spark, monkeypatch):
    members = spark.createDataFrame([(m, g) for g in range(40) for m in {g % 7, g % 5 + 3, g % 11, g % 3 + 20}] + [(None, 1), (3, None)], "m long, g long")
    found = lambda least: rows(gr.project_bipartite(members, "m", "g", least), "src", "dst", "support")
    in_lists = found(1), found(3)
    monkeypatch.setattr(gr, "_met_in_lists", None)
    monkeypatch.setattr(gr, "LISTED", 0)
    assert (found(1), found(3)) == in_lists and in_lists[1]


def test_similarities_of_mapped_sets_are_those_of_joined_ones(spark, monkeypatch):
    from localcomm.operators import overlap

    rng = np.random.default_rng(3)
    sets = [(i, [str(x) for x in rng.integers(0, 40, rng.integers(0, 12))] + [f"own{i}"] * (i % 2)) for i in range(60)]
    nodes = spark.createDataFrame([*sets, (60, None), (61, []), (62, ["1", None]), (63, [None, "2", ""]), (64, [""])], "node long, attrs array<string>")
    pairs = {(min(a, b), max(a, b)) for a, b in rng.integers(0, 66, (400, 2)).tolist() if a != b} | {(60, 61), (62, 63), (63, 64), (5, 99), (98, 99)}
    edges = spark.createDataFrame(sorted(pairs), "src long, dst long")
    cols = ("src", "dst", "sim", "is_structural")
    joined = rows(gr.attribute_graph(nodes, edges), *cols)
    monkeypatch.setattr(gr, "SETS_FROM", 0)
    monkeypatch.setattr(gr, "with_sets", None)  # no set travels with an edge
    assert rows(gr.attribute_graph(nodes, edges), *cols) == joined and len({r[2] for r in joined}) > 9
    monkeypatch.setattr(overlap, "PART_MEMBERS", 50)  # many parts
    where = overlap.written(nodes.selectExpr("node", "array_sort(array_distinct(attrs)) AS x").where("size(x) > 0"))
    few, many = overlap.Sets(*where), overlap.Sets(*where)
    ends = np.array(sorted(pairs)).T
    monkeypatch.setattr(overlap, "MARKS", 1)  # one vertex's members at a time
    one = few.similar(*ends)
    monkeypatch.setattr(overlap, "MARKS", 10**6)
    np.testing.assert_array_equal(one, many.similar(*ends))


def test_a_mapped_graph_is_written_once_in_few_bytes(parts, monkeypatch):
    import os

    edges, combined, _, _ = parts
    monkeypatch.setattr(mapped, "PART_ROWS", 100)
    monkeypatch.setattr(mapped, "DEAL_ROWS", 70)
    coded = mapped.layout(combined)
    assert sum(os.path.getsize(f"{coded.folder}/{f}") for f in os.listdir(coded.folder)) <= 10 * coded.rows + 24 * coded.n + 16 * combined.select("w").distinct().count()
    by_hand = sorted((a, b, w) for s, d, w in rows(combined, "src", "dst", "w") for a, b in ((s, d), (d, s)))
    g = mapped.MappedGraph(coded)
    assert [(int(g.node[i]), int(g.node[j]), round(w, 9)) for i, j, w in zip(np.repeat(np.arange(g.n), np.diff(g.end, prepend=0)), g.dst, g.w[:], strict=True)] == by_hand
    monkeypatch.setattr(mapped, "CODES", 0)
    plain = mapped.layout(combined.select("*"))
    assert coded.coded and not plain.coded and arrays(coded) == arrays(plain)
    assert mapped.layout(combined.where("src < 0")).rows == 0


def test_moves_of_uneven_weights_are_those_of_a_plain_search(spark, monkeypatch):
    hub = [(0, i, 1.0 if i % 50 else 900.0 * (i < 200) + 1) for i in range(1, 800)]
    g = mapped.MappedGraph(mapped.layout(spark.createDataFrame(hub, "src long, dst long, w double")))
    u = np.concatenate([np.linspace(0, 2_147_483_646, 5000).astype(np.int64), [0, 1, 2_147_483_646]])
    hi = np.cumsum([round(1000 * w) for *_, w in hub])
    want = np.searchsorted(hi, u * hi[-1] // 2_147_483_647, side="right") + 1
    for near in (0, 16, 10_000):
        monkeypatch.setattr(mapped, "NEAR", near)
        assert g.node[g.moves(np.zeros(len(u), np.int64), u)].tolist() == want.tolist()


def test_draws_and_counts_of_arrays(spark):
    def plain(keys, x=42):
        for k in keys:
            x = (x * 48271 + k % 2147483647) % 2147483647
            for c in (12345, 67891, 424243):
                x = (x * x + x * 65537 + c) % 2147483647
        return x

    keys = [(-5, 3, 2147483646), (2**40, 0, 1), (2147483647, 2147483648, -1)]
    assert walks.draw_numpy(list(np.array(keys).T), 42).tolist() == [plain(k) for k in keys]
    w, n = np.array([3, 3, 4, 4, 4, 9]), np.array([7, 7, 7, -2, 7, -2])
    want = ([-2, 7], [2, 2])
    assert tuple(x.tolist() for x in walks._counted(w, n)) == want
    far = np.where(n < 0, -(2**62), 2**62 - 1)  # pairs that don't fit one number
    assert walks._counted(w, far)[1].tolist() == want[1]
