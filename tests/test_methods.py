"""Worked examples, lemmas and brute force for the resolution methods."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from crowdlink.config import Config
from crowdlink.graph import components
from crowdlink.operators import baselines, clustering, kernels, measures, questions, reliability, votes, worlds


def edges_of(spark, rows):
    return spark.createDataFrame([(u, w, float(p)) for u, w, p in rows], "u long, w long, p double")


def clusters_of(spark, groups):
    return spark.createDataFrame([(r, min(g)) for g in groups for r in g], "rid long, cid long")


def test_reliability_of_four_records(spark):
    edges = edges_of(spark, [(0, 1, 0.9), (1, 2, 0.8), (0, 3, 0.2), (1, 3, 0.6)])
    clusters = clusters_of(spark, [[0, 1, 2], [3]])
    lab = votes.labelled(edges, clusters)
    assert {r.cid: round(r.connect, 6) for r in reliability.connectivity(lab, clusters).collect()} == {0: 0.72, 3: 1.0}
    assert round(reliability.disconnect(lab).first().disc, 6) == 0.88
    assert round(reliability.reliability(lab, clusters).first().reliability, 6) == -0.198185


def eight(spark):
    return edges_of(spark, [(0, 1, 0.8), (2, 3, 0.8), (4, 5, 0.8), (6, 7, 0.8), (0, 2, 0.3), (1, 3, 0.6), (4, 6, 0.3), (5, 7, 0.7), (0, 4, 0.0), (2, 4, 0.0)])


def test_eight_records_merge_and_next_pair(spark):
    edges = eight(spark)
    records = spark.range(8).withColumnRenamed("id", "rid")
    found = clustering.scc(edges, records)
    assert {r.rid: r.cid for r in found.collect()} == {0: 0, 1: 0, 2: 2, 3: 2, 4: 4, 5: 4, 6: 6, 7: 6}
    lab = votes.labelled(edges, found)
    probs = {(r.c1, r.c2): round(r.prob, 6) for r in clustering.merge_probability(lab).collect()}
    assert probs[0, 2] == 0.391304 and probs[4, 6] == 0.5
    gains = {(r.c1, r.c2): round(r.prio, 6) for r in questions.across_units(lab).collect()}
    assert gains[0, 2] == 0.086186 and gains[4, 6] == 0.102373
    best = questions.next_questions(lab, found, 1, Config(edgeless="skip")).first()
    assert (best.c1, best.c2) == (4, 6)


@pytest.mark.parametrize("mode", ["exact", "contract"])
def test_clustering_equals_global_greedy(spark, mode):
    rng = np.random.default_rng(5)
    rows, expected = [], {}
    for g in range(25):
        base = 100 * g
        pairs = [(a, b) for a, b in itertools.combinations(range(9), 2) if rng.random() < 0.5]
        p = rng.integers(0, 6, len(pairs)) / 5
        a, b = (np.array(x) for x in zip(*pairs, strict=True))
        labels = kernels.agglomerate(9, a, b, kernels.log_odds(p))
        least = {c: min(np.flatnonzero(labels == c).tolist()) for c in set(labels.tolist())}
        expected |= {base + n: base + least[c] for n, c in enumerate(labels.tolist())}
        rows += [(base + x, base + y, q) for (x, y), q in zip(pairs, p.tolist(), strict=True)]
    records = spark.createDataFrame([(r,) for r in expected], "rid long")
    found = {r.rid: r.cid for r in clustering.scc(edges_of(spark, rows), records, Config(scc_mode=mode)).collect()}
    assert found == expected


def test_blocks_of_a_large_component_keep_the_greedy_order(spark):
    rng = np.random.default_rng(8)
    pairs = [x for x in itertools.combinations(range(18), 2) if rng.random() < 0.6]
    p = rng.integers(0, 6, len(pairs)) / 5
    a, b = (np.array(x) for x in zip(*pairs, strict=True))
    labels = kernels.agglomerate(18, a, b, kernels.log_odds(p)).tolist()
    records = spark.createDataFrame([(r,) for r in range(18)], "rid long")
    edges = edges_of(spark, [(x, y, q) for (x, y), q in zip(pairs, p.tolist(), strict=True)])
    for most in (60, 20):  # several nodes in a block; single pairs
        found = {r.rid: r.cid for r in clustering.scc(edges, records, Config(scc_mode="exact", max_component=most)).collect()}
        assert [found[n] for n in range(18)] == labels


def test_unsafe_contraction_example():
    a, b = np.array([0, 0, 1, 2, 1]), np.array([1, 2, 2, 3, 3])
    labels = kernels.agglomerate(4, a, b, np.array([5, 4.9, 4.9, 6, -11.0]))
    assert labels.tolist() == [0, 0, 2, 2]


def brute_connect(n, a, b, p):
    total = 0.0
    for bits in itertools.product([0, 1], repeat=len(p)):
        on = np.array(bits, bool)
        if len(set(kernels.components(n, a[on], b[on]).tolist())) == 1:
            total += float(np.prod(np.where(on, p, 1 - p)))
    return total


def test_connectivity_exact_and_sampled():
    rng = np.random.default_rng(2)
    for _ in range(20):
        pairs = [x for x in itertools.combinations(range(5), 2) if rng.random() < 0.7] or [(0, 1)]
        a, b = (np.array(x) for x in zip(*pairs, strict=True))
        p = rng.random(len(pairs))
        exact = brute_connect(5, a, b, p)
        assert kernels.connect_exact(5, a, b, p) == pytest.approx(exact, abs=1e-12)
        s = kernels.Sample.draw(np.arange(5), a, b, p, 4000, 1)
        assert abs(s.connect - exact) < 4 * np.sqrt(0.25 / 4000)
        for x, y in itertools.combinations(range(5), 2):
            if (x, y) not in pairs:
                joined = brute_connect(5, np.append(a, x), np.append(b, y), np.append(p, 1.0))
                assert abs(s.connect_with()[x, y] - joined) < 4 * np.sqrt(0.25 / 4000)


def test_four_cycle_asks_the_better_chord():
    a, b, p = np.array([0, 1, 2, 0]), np.array([1, 2, 3, 3]), np.array([0.9, 0.8, 0.6, 0.7])
    assert kernels.connect_exact(4, a, b, p) == pytest.approx(0.7428)
    s = kernels.Sample.draw(np.arange(4), a, b, p, 20000, 3)
    assert s.connect_with()[1, 3] > s.connect_with()[0, 2]


def test_worlds_and_partitions(spark):
    assert [r.partitions for r in worlds.partition_counts(spark).orderBy("n").collect()] == [1, 2, 5, 15, 52, 203]
    assert [len(list(kernels.partitions(n))) for n in range(1, 7)] == [1, 2, 5, 15, 52, 203]
    triangle = edges_of(spark, [(0, 1, 0.8), (0, 2, 0.4), (1, 2, 0.4)])
    w = worlds.possible_worlds(triangle)
    assert worlds.world_probability(w).agg({"prob": "sum"}).first()[0] == pytest.approx(1)
    assert worlds.not_closed(w).count() == 3
    best, score = kernels.best_partition(3, np.array([0, 0, 1]), np.array([1, 2, 2]), np.array([0.8, 0.4, 0.4]))
    assert best.tolist() == [0, 0, 1] and score == pytest.approx(0.288)
    with pytest.raises(ValueError):
        worlds.possible_worlds(spark.range(21).selectExpr("id u", "id + 1 w", "0.5D p"))


def test_agreeing_answer_keeps_the_optimum():
    rng = np.random.default_rng(9)
    for _ in range(60):
        pairs = list(itertools.combinations(range(5), 2))
        asked = [x for x in pairs if rng.random() < 0.6]
        free = [x for x in pairs if x not in asked]
        if not asked or not free:
            continue
        a, b = (np.array(x) for x in zip(*asked, strict=True))
        p = rng.random(len(asked))
        best, score = kernels.best_partition(5, a, b, p)
        u, w = free[0]
        q = 0.9 if best[u] == best[w] else 0.1
        again, after = kernels.best_partition(5, np.append(a, u), np.append(b, w), np.append(p, q))
        assert after == pytest.approx(score * 0.9)


def test_gains_never_fall(spark):
    units = spark.createDataFrame([(0, 1, 0.3), (0, 2, 0.9)], "c1 long, c2 long, disc double")
    for c2 in (1, 2):
        g = [r.gain for r in questions.gain_curve(units).where(f"c2 = {c2}").orderBy("q").collect()]
        assert g == sorted(g) and abs(g[0]) < 1e-12 and g[-1] == max(g)


def test_votes_are_canonical_and_counted(spark):
    rows = [(1, 2, 7, True), (2, 1, 7, True), (3, 3, 1, True), (1, 2, 8, False), (4, 5, 1, None), (2, 6, 1, False)]
    v = votes.canonical_votes(spark.createDataFrame(rows, "u long, w long, worker long, yes boolean"))
    e = {(r.u, r.w): (r.n_votes, r.n_yes, r.p) for r in votes.build_edges(v).collect()}
    assert e == {(1, 2): (2, 1, 0.5), (2, 6): (1, 0, 0.0)}
    assert {r.p for r in votes.build_edges(v, "majority").collect()} == {0.0}
    assert {r.p for r in votes.build_edges(v, "fixed_accuracy").collect()} == {0.1}
    more = votes.add_answers(votes.build_edges(v), spark.createDataFrame([(2, 6, 2, True)], "u long, w long, worker long, yes boolean"))
    assert {(r.u, r.w): r.p for r in more.collect()} == {(1, 2): 0.5, (2, 6): 0.5}


def test_bottleneck_equals_all_simple_paths(spark):
    rng = np.random.default_rng(4)
    for _ in range(40):
        pairs = [x for x in itertools.combinations(range(5), 2) if rng.random() < 0.6] or [(0, 1)]
        p = dict(zip(pairs, (rng.integers(0, 11, len(pairs)) / 10).tolist(), strict=True))
        a, b = (np.array(x) for x in zip(*pairs, strict=True))
        pos, neg = kernels.bottleneck(5, a, b, np.array(list(p.values())))
        for x, y in itertools.combinations(range(5), 2):
            best = [0.0, 0.0]
            for k in range(4):
                for mid in itertools.permutations([z for z in range(5) if z not in (x, y)], k):
                    path = [x, *mid, y]
                    ws = [p.get((min(s), max(s))) for s in itertools.pairwise(path)]
                    if None in ws:
                        continue
                    refused = [w for w in ws if w <= 0.5]
                    if not refused:
                        best[0] = max(best[0], min(ws))
                    elif len(refused) == 1 and refused[0] < 0.5:
                        best[1] = max(best[1], min(1 - w if w < 0.5 else w for w in ws))
            assert pos[x, y] == pytest.approx(best[0])
            assert (pos[x, y] > neg[x, y]) == (best[0] > 0 and best[0] > best[1] - 1e-12)  # equal paths match


def test_components_of_long_paths_and_stars(spark, monkeypatch):
    import crowdlink.graph as graph

    rows = [(i, i + 1) for i in range(60)] + [(1000, 1000 + k) for k in range(1, 40)] + [(5000, 5000), (None, 3)]
    edges = spark.createDataFrame(rows, "u long, w long")
    small = {r.id: r.component for r in components(edges).collect()}
    monkeypatch.setattr(graph, "SMALL", -1)
    large = {r.id: r.component for r in graph.components(edges).collect()}
    assert small == large == {**dict.fromkeys(range(61), 0), **dict.fromkeys(range(1000, 1040), 1000), 5000: 5000}


def test_scores_count_pairs_by_sizes(spark):
    clusters = clusters_of(spark, [[0, 1, 2], [3, 4], [5]])
    gold = spark.createDataFrame([(0, "a"), (1, "a"), (2, "b"), (3, "b"), (4, "b"), (5, "c")], "rid long, entity string")
    r = measures.pair_scores(clusters, gold).first()
    assert (r.correct, r.reported, r.matching) == (2, 4, 4)
    alone = measures.pair_scores(clusters_of(spark, [[0], [1]]), gold).first()
    assert alone.f1 == 0


def test_edge_cases_of_graphs(spark):
    records = spark.createDataFrame([(1,)], "rid long")
    empty = edges_of(spark, [])
    assert [tuple(r) for r in clustering.scc(empty, records).collect()] == [(1, 1)]
    half = edges_of(spark, [(1, 2, 0.5)])
    two = spark.createDataFrame([(1,), (2,)], "rid long")
    assert {r.cid for r in clustering.scc(half, two).collect()} == {1, 2}
    assert {r.cid for r in baselines.pivot_clusters(edges_of(spark, [(1, 2, 0.9)]), two).collect()} == {1}
    refused = votes.labelled(edges_of(spark, [(1, 2, 0.0)]), clusters_of(spark, [[1], [2]]))
    assert reliability.disconnect(refused).first().disc == 1.0


def test_gap_representative_skips_asked_pairs(spark):
    clusters = clusters_of(spark, [[0, 1], [2, 3]])
    lab = votes.labelled(edges_of(spark, [(0, 2, 0.1), (0, 3, 0.1), (1, 2, 0.1)]), clusters)
    r = questions.gap_representatives(reliability.disconnect(lab), lab, clusters).collect()
    assert [(x.u, x.w) for x in r] == [(1, 3)]
    full = votes.labelled(edges_of(spark, [(u, w, 0.1) for u in (0, 1) for w in (2, 3)]), clusters)
    assert questions.gap_representatives(reliability.disconnect(full), full, clusters).count() == 0


def test_edgeless_pairs_are_all_found(spark):
    clusters = clusters_of(spark, [[n] for n in range(9)])
    every = list(itertools.combinations(range(9), 2))
    lab = votes.labelled(edges_of(spark, [(u, w, 0.1) for u, w in every[:30]]), clusters)
    for count, many in ((2, 2), (6, 6), (50, 6)):
        found = {(r.c1, r.c2) for r in questions.edgeless_candidates(lab, clusters, count).collect()}
        assert len(found) == many and found <= set(every[30:])
    full = votes.labelled(edges_of(spark, [(u, w, 0.1) for u, w in every]), clusters)
    assert questions.edgeless_candidates(full, clusters, 5).count() == 0


def test_pivots_settle_long_chains(spark):
    order = [r.rid for r in spark.range(90).withColumnRenamed("id", "rid").orderBy(votes.unit_hash(42, F.col("rid")), "rid").collect()]
    edges = edges_of(spark, [(min(x), max(x), 0.9) for x in itertools.pairwise(order)])  # two records settle in a round
    records = spark.createDataFrame([(r,) for r in order], "rid long")
    assert baselines.pivot_clusters(edges, records).count() == 90


def test_walks_draw_the_worlds_that_all_edges_give():
    rng = np.random.default_rng(6)
    for n in (2, 5, 7):
        pairs = [x for x in itertools.combinations(range(n), 2) if rng.random() < 0.7] or [(0, 1)]
        a, b = (np.array(x) for x in zip(*pairs, strict=True))
        p = rng.random(len(pairs))
        ids = np.arange(n) * 3 + 1
        s = kernels.Sample.draw(ids, a, b, p, 300, 5)
        assert kernels.walked(ids, a, b, p, 300, 5) == pytest.approx(s.connect)
        i, j = np.triu_indices(n, 1)
        assert s.connect_pairs(i, j) == pytest.approx(s.connect_with()[i, j], abs=1e-6)


def test_inside_candidates_of_pairs_bare_and_sampled_clusters(spark):
    clusters = clusters_of(spark, [[0, 1], [2, 3], list(range(10, 40))])
    lab = votes.labelled(edges_of(spark, [(2, 3, 0.9), *((10 + k, 11 + k, 0.9) for k in range(29))]), clusters)
    found = {(r.c1, r.u, r.w): r.prio for r in questions.inside_candidates(lab, clusters, Config(samples=50), 2).collect()}
    assert found[0, 0, 1] == pytest.approx(9) and not any(c == 2 for c, _, _ in found) and sum(c == 10 for c, _, _ in found) == 2
    few = questions.inside_candidates(lab, clusters, Config(samples=50, pair_sample=7), 100).where("c1 = 10").collect()
    again = questions.inside_candidates(lab, clusters, Config(samples=50, pair_sample=7), 100).where("c1 = 10").collect()
    assert len({(r.u, r.w) for r in few}) == 7 and few == again and all(r.w - r.u > 1 for r in few)


def test_singletons_give_as_many_questions_as_asked_for(spark):
    for n, count in ((2, 5), (5, 3), (7, 100)):
        alone = clusters_of(spark, [[k] for k in range(n)])
        found = questions.next_questions(votes.labelled(edges_of(spark, []), alone), alone, count).collect()
        assert len({(r.u, r.w) for r in found}) == min(count, n * (n - 1) // 2)


def test_loop_runs_to_the_complete_graph_and_to_a_target(spark):
    from crowdlink.plans.loop import resolve
    from crowdlink.sources.workloads import simulate_votes

    records = spark.range(6).select(F.col("id").alias("rid"))
    gold = records.select("rid", (F.col("rid") % 2).cast("string").alias("entity"))
    ask = lambda p: simulate_votes(p.withColumn("same", F.col("u") % 2 == F.col("w") % 2), 5, 0.0)
    clusters, edges, log = resolve(records, ask, None, Config(batch=8, initial="none"))
    assert edges.count() == 15 and log[-1]["asked"] == 15
    assert {r.rid: r.cid for r in clusters.collect()} == {k: k % 2 for k in range(6)}
    _, edges, log = resolve(records, ask, None, Config(batch=4, initial="spanning", target_f1=1.0), gold=gold)
    assert edges.count() < 15 and edges.join(spark.createDataFrame([(0, 1), (4, 5)], "u long, w long"), ["u", "w"]).count() == 2
    _, edges, log = resolve(records, ask, None, Config(batch=4, initial="all", budget=9))
    assert edges.count() == 15 and not log


def test_kept_queue_equals_a_rebuilt_one(spark):
    rng = np.random.default_rng(3)
    clusters = clusters_of(spark, [[0, 1, 2, 3], [4, 5, 6], [7, 8], [9]])
    every = list(itertools.combinations(range(10), 2))
    some = [x for x in every if rng.random() < 0.5]
    edges = edges_of(spark, [(u, w, rng.integers(1, 5) / 5) for u, w in some])
    free = [x for x in every if x not in some]
    more = edges.unionByName(edges_of(spark, [(*free[0], 0.8), (*free[-1], 0.2)]))
    k = Config(samples=100)
    queue = questions.unit_queue(votes.labelled(edges, clusters), clusters, 3, k)
    touched = questions.units_of(spark.createDataFrame([free[0], free[-1]], "u long, w long"), clusters)
    now = votes.labelled(more, clusters)
    kept = questions.refresh_units(queue, questions.unit_queue(now, clusters, 3, k, touched), touched)
    key = lambda df: sorted((r.kind, r.c1, r.c2, r.u, r.w, round(r.prio, 9)) for r in df.collect())
    assert key(kept) == key(questions.unit_queue(now, clusters, 3, k))


def test_fixed_accuracy_stays_with_a_graph(spark):
    rows = [(1, 2, 7, True), (1, 3, 7, False)]
    graph = votes.UncertainGraph.of(spark.range(5).withColumnRenamed("id", "rid"), spark.createDataFrame(rows, "u long, w long, worker long, yes boolean"), "fixed_accuracy", 0.7)
    after = graph.add(spark.createDataFrame([(2, 3, 1, True)], "u long, w long, worker long, yes boolean"))
    assert {(r.u, r.w): round(r.p, 6) for r in after.edges.collect()} == {(1, 2): 0.7, (1, 3): 0.3, (2, 3): 0.7}


def test_bottleneck_of_named_pairs_equals_the_matrix(spark):
    rng = np.random.default_rng(11)
    pairs = [x for x in itertools.combinations(range(8), 2) if rng.random() < 0.5]
    edges = edges_of(spark, [(u, w, rng.integers(0, 6) / 5) for u, w in pairs])
    records = spark.range(8).withColumnRenamed("id", "rid")
    asked = spark.createDataFrame(list(itertools.combinations(range(8), 2)), "u long, w long")
    key = lambda df: sorted((r.u, r.w, r.pos, r.neg, r.decision) for r in df.collect())
    assert key(baselines.bottleneck_relation(edges, records, asked, few=0)) == key(baselines.bottleneck_relation(edges, records))
    with pytest.raises(ValueError):
        baselines.bottleneck_relation(edges, records, few=0)


def test_refined_pivots_and_mean_merges_gain(spark):
    rows = [(0, 1, 0.9), (0, 2, 0.6), (1, 2, 0.1), (2, 3, 0.9), (0, 3, 0.2), (1, 3, 0.0)]
    edges, records = edges_of(spark, rows), spark.range(4).withColumnRenamed("id", "rid")
    rough = clusters_of(spark, [[0, 1, 2], [3]])
    fine = baselines.pivot_refined(edges, records, rough)
    assert {r.rid: r.cid for r in fine.collect()} == {0: 0, 1: 0, 2: 2, 3: 2}
    assert {r.rid: r.cid for r in clustering.average_odds(edges, records).collect()} == {0: 0, 1: 0, 2: 2, 3: 2}
    found = clustering.scc(edges, records, Config(scc_mode="rounds"))
    assert {r.rid: r.cid for r in found.collect()} == {0: 0, 1: 0, 2: 2, 3: 2}


def test_levels_and_triangles(spark):
    from crowdlink.graph import levels, triangles

    rng = np.random.default_rng(5)
    pairs = [x for x in itertools.combinations(range(12), 2) if rng.random() < 0.25]
    e = spark.createDataFrame(pairs + [(w, u) for u, w in pairs[:3]], "u long, w long")
    near = {x: {b if a == x else a for a, b in pairs if x in (a, b)} for x in range(12)}
    expected = sorted(t for t in itertools.combinations(range(12), 3) if all(y in near[x] for x, y in itertools.combinations(t, 2)))
    assert sorted(tuple(r) for r in triangles(e).collect()) == expected
    dist, todo = {0: 0}, [0]
    for x in todo:
        for y in near[x] - dist.keys():
            dist[y] = dist[x] + 1
            todo.append(y)
    assert {r.id: r.level for r in levels(e, spark.createDataFrame([(0,)], "id long")).collect()} == dist


def test_runs_and_dataframes_choose_alike(spark):
    """The in-task method of the experiments and the operators on DataFrames: same clusters, same gains."""
    from crowdlink.plans import simulate

    rng = np.random.default_rng(21)
    u, w = np.triu_indices(14, 1)
    ratio = np.where(u % 3 == w % 3, rng.choice([0.6, 0.8, 1.0], len(u)), rng.choice([0.0, 0.2, 0.4], len(u)))
    pool = simulate.Pool(14, u, w, ratio, (ratio > 0.5).astype(float), 42)
    pool.asked[rng.random(len(u)) < 0.45] = True
    method = simulate.Reliability(pool, 1000)
    label, _ = method.cluster(None, None)
    edges = edges_of(spark, [(int(a), int(b), q) for a, b, q in zip(*pool.edges(ratio), strict=True)])
    records = spark.range(14).withColumnRenamed("id", "rid")
    found = clustering.scc(edges, records)
    least = {c: min(np.flatnonzero(label == c).tolist()) for c in set(label.tolist())}
    assert {r.rid: r.cid for r in found.collect()} == {n: least[c] for n, c in enumerate(label.tolist())}
    lab, k = votes.labelled(edges, found), Config(exact_gain_edges=0, exact_max_edges=0)
    queue = questions.unit_queue(lab, found, 100, k).collect()
    best = sorted((r.prio for r in questions.next_questions(lab, found, 6, k).collect()), reverse=True)
    # all pairs of two clusters gain the same, so any of them may stand for the others
    gains = {(r.u, r.w) if r.kind == "inside" else (r.c1, r.c2): r.prio for r in queue}
    unit = lambda c: (int(u[c]), int(w[c])) if label[u[c]] == label[w[c]] else tuple(sorted((least[label[u[c]]], least[label[w[c]]])))
    assert sorted((gains.get(unit(c), 9.0) for c in method.choose(label, 6)), reverse=True) == pytest.approx(best, abs=1e-6)
    assert method.reliability(label) == pytest.approx(reliability.reliability(lab, found, k).first().reliability, abs=1e-6)


def noisy_pool(sizes, share, seed, voters=5, err=0.1):
    """A pool of all matching pairs and a share of the others, with votes of that error, and the entities."""
    from crowdlink.plans import simulate

    rng = np.random.default_rng(seed)
    entity = rng.permutation(np.repeat(np.arange(len(sizes)), sizes))
    u, w = np.triu_indices(len(entity), 1)
    same = entity[u] == entity[w]
    kept = same | (rng.random(len(u)) < share)
    u, w, same = u[kept], w[kept], same[kept]
    yes = rng.binomial(voters, np.where(same, 1 - err, err))
    return simulate.Pool(len(entity), u, w, yes / voters, (2 * yes > voters).astype(float), seed), entity


@pytest.mark.parametrize("levels", [5, 1])
def test_growing_clusters_are_those_of_greedy_on_all_links(levels):
    from crowdlink.operators import kernels
    from crowdlink.plans import simulate

    for seed in range(6):
        pool, _ = noisy_pool([9, 6, 5, 4, 3, 2, 2, 1], 0.7, seed, err=0.25)
        odds = kernels.log_odds(pool.ratio if levels > 1 else np.where(pool.majority > 0.5, 0.9, 0.1))
        growing = simulate.Growing(pool.n, np.unique(odds))
        for end in range(7, len(odds) + 7, 7):
            at, some = pool.order[:end], pool.order[end - 7 : end]
            found = growing.add(pool.u[some], pool.w[some], odds[some])
            assert found.tolist() == kernels.agglomerate(pool.n, pool.u[at], pool.w[at], odds[at]).tolist()


@pytest.mark.parametrize("method", ["random", "reliability", "bdense"])
def test_a_round_merges_again_only_what_its_answers_change(method, monkeypatch):
    from crowdlink.plans import simulate

    seen, merge = [], simulate.agglomerate
    monkeypatch.setattr(simulate, "agglomerate", lambda n, a, *more, **named: seen.append(len(a)) or merge(n, a, *more, **named))
    pool, entity = noisy_pool([3] * 60, 0.2, 5, err=0.02)
    rounds = simulate.run(pool, entity, method, 5, 1500, 50, None, most_rounds=20)
    assert len(rounds) == 21 and max(seen[2:]) < 200  # of more than 1,500 links; the first clustering takes two calls at most


@pytest.mark.parametrize("tie", ["hash", "size"])
def test_reliability_keeps_what_answers_do_not_change(tie, monkeypatch):
    """Choices and scores from what is kept are those of a look at all pairs, which early rounds do not take."""
    from crowdlink.plans import simulate

    pool, _ = noisy_pool([9, 7, *[4] * 6, *[2] * 15], 0.5, 3, err=0.2)
    looks, look = [], simulate.Reliability._choose
    monkeypatch.setattr(simulate.Reliability, "_choose", lambda *x: looks.append(1) or look(*x))
    pool.asked[pool.order[:40]] = True
    method = simulate.Reliability(pool, 60, tie=tie)
    label, _ = method.cluster(None, None)
    for n in range(300):
        other = simulate.Reliability(pool, 60, tie=tie)
        other.cluster(None, None)
        assert method.reliability(label) == pytest.approx(other.reliability(label), rel=1e-12)
        fresh = method.choose(label, 6)
        assert len(looks) == 0 or n >= 20
        assert fresh.tolist() == look(other, label, 6).tolist()
        if not len(fresh):
            break
        pool.asked[fresh] = True
        label, _ = method.cluster(label, fresh)
    assert pool.asked.all() and looks


def test_best_paths_without_a_matrix():
    """Clusters and choices of best paths, against the matrices of all pairs of records."""
    from crowdlink.operators import kernels
    from crowdlink.plans import simulate

    for seed, err in itertools.product(range(6), (0.1, 0.3)):
        pool, _ = noisy_pool([8, 6, 5, 4, 3, 2, 2, 1, 1], 0.6, seed, err=err)
        for end in (0, 5, 20, 60, 120, 200, len(pool.u) - 3):
            pool.asked[pool.order[:end]] = True
            method = simulate.Bottleneck(pool)
            label, _ = method.cluster(None, None)
            pos, neg = kernels.bottleneck(pool.n, *pool.edges(pool.ratio))
            assert label.tolist() == kernels.components(pool.n, *np.nonzero(np.triu(pos > neg, 1))).tolist()
            free = np.flatnonzero(~pool.asked)
            x, y = pos[pool.u[free], pool.w[free]], neg[pool.u[free], pool.w[free]]
            best = free[np.lexsort((pool.hash[free], -np.maximum(x, np.where(x <= y, 1 - y, 0))))]
            assert method.choose(label, 9).tolist() == best[:9].tolist()


def test_best_paths_take_memory_for_pairs_that_may_be_asked():
    """Not for all pairs of 6,000 records, which are 576 MB in two matrices."""
    import tracemalloc

    from crowdlink.plans import simulate

    u = np.repeat(np.arange(0, 6000, 3), 2)
    w, yes = u + np.tile([1, 2], 2000), np.tile([1.0, 0.8], 2000)
    tracemalloc.start()
    rounds = simulate.run(simulate.Pool(6000, u, w, yes, np.ones(4000), 1), np.arange(6000) // 3, "minmax", 500, 2000, 10, 1.0)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert rounds["f1"].iloc[-1] == 1 and most < 50e6


def test_pivots_choose_without_a_look_at_all_pairs(monkeypatch):
    from crowdlink.plans import simulate

    looks, look = [], simulate.Pivot._choose
    monkeypatch.setattr(simulate.Pivot, "_choose", lambda *x: looks.append(1) or look(*x))
    for seed in range(4):
        pool, _ = noisy_pool([9, 7, *[4] * 6, *[2] * 15], 0.5, seed, err=0.25)
        pool.asked[pool.order[:40]] = True
        method, n = simulate.Pivot(pool), 0
        while len(fresh := look(method, label := method.cluster(None, None)[0], 6)):
            looks.clear()
            assert method.choose(label, 6).tolist() == fresh.tolist()
            assert not looks or n > 20
            pool.asked[fresh] = True
            n += 1
        a, b, q = pool.edges(pool.ratio)
        x, y = np.minimum(a, b).astype(np.int64), np.maximum(a, b).astype(np.int64)
        assert method._merged(x, y, 2 * q - 1).tolist() == kernels.agglomerate(pool.n, x, y, 2 * q - 1).tolist()


@pytest.mark.parametrize("spread", [True, False])
def test_density_keeps_what_answers_do_not_change(spread, monkeypatch):
    from crowdlink.plans import simulate

    looks, look = [], simulate.Density._choose
    monkeypatch.setattr(simulate.Density, "_choose", lambda *x: looks.append(1) or look(*x))
    for seed in range(4):
        pool, _ = noisy_pool([9, 7, *[4] * 6, *[2] * 15], 0.5, seed, err=0.25)
        pool.asked[pool.order[:40]] = True
        method, n = simulate.Density(pool, spread=spread), 0
        looks.clear()
        label, _ = method.cluster(None, None)
        while len(fresh := method.choose(label, 6)):
            assert not looks or n > 100
            assert fresh.tolist() == look(method, label, 6).tolist()
            pool.asked[fresh] = True
            label, _ = method.cluster(label, fresh)
            n += 1
        assert pool.asked.all()


def test_closure_passes_each_pair_once():
    """Rounds of closure until no pair is open, against its definition on all asked pairs."""
    from crowdlink.operators import kernels
    from crowdlink.plans import simulate

    pool, _ = noisy_pool([6, 5, 4, 3, 2, 2, 1, 1, 1], 0.6, 8, err=0.2)
    pool.asked[pool.order[:9]] = True
    method = simulate.Transitive(pool)
    label, _ = method.cluster(None, None)
    while True:
        yes = pool.asked & (pool.majority > 0.5)
        assert label.tolist() == kernels.components(pool.n, pool.u[yes], pool.w[yes]).tolist()
        keys = simulate.unit_keys(label, pool.u, pool.w)
        open_ = ~pool.asked & (label[pool.u] != label[pool.w]) & ~np.isin(keys, keys[pool.asked & ~yes])
        fresh = method.choose(label, 4)
        assert fresh.tolist() == [x for x in pool.order.tolist() if open_[x]][:4]
        if not len(fresh):
            break
        pool.asked[fresh] = True
        label, _ = method.cluster(label, fresh)


def test_packed_pairs_come_back():
    import pyarrow as pa

    from crowdlink.plans import experiments

    rng = np.random.default_rng(4)
    t = pa.table({"vseed": pa.array(rng.integers(0, 2, 900), pa.int32()), "verr": pa.array([0.05] * 900), "u": rng.integers(-(2**40), 2**40, 900), "w": rng.integers(0, 90, 900), "n_yes": pa.array(rng.integers(0, 11, 900), pa.int32())})
    parts = pa.Table.from_batches(list(experiments.packed(iter(t.to_batches(100)), 250))).to_pandas()
    for seed, g in t.to_pandas().groupby("vseed"):
        back = experiments.unpacked(parts["pairs"][parts["vseed"] == seed])
        assert [x.tolist() for x in back] == [g[c].tolist() for c in ("u", "w", "n_yes")]


def test_a_cluster_session_must_name_its_folder(spark):
    from crowdlink import storage

    class Bare:
        conf = {"spark.master": "spark://host:7077"}

    with pytest.raises(ValueError):
        storage.shared_dir(Bare())
    t = storage.cut(spark.range(3))
    assert t.count() == 3
    storage.forget(t)
    with pytest.raises(Exception):  # noqa: B017
        spark.read.parquet(t.cut_path).count()


def test_merges_by_a_matrix_equal_those_by_links():
    rng = np.random.default_rng(5)
    for n in (2, 9, 40, 90):
        u, w = np.triu_indices(n, 1)
        keep = rng.random(len(u)) < 0.7
        odds = np.round(rng.choice([-2.0, -1.0, 0.5, 1.0, 3.0], len(u)), 12)[keep]
        by_links = kernels.agglomerate(n, u[keep], w[keep], odds)
        assert kernels.agglomerate_dense(n, u[keep], w[keep], odds).tolist() == by_links.tolist()


def test_components_that_fit_a_task_take_no_rounds(spark, monkeypatch):
    def no(*args):
        raise AssertionError("a round over all links")

    monkeypatch.setattr(clustering, "safe_merges", no)
    edges = edges_of(spark, [(0, 1, 0.9), (1, 2, 0.8), (3, 4, 0.7), (2, 3, 0.1)])
    found = clustering.scc(edges, spark.range(6).withColumnRenamed("id", "rid"))
    assert {r.rid: r.cid for r in found.collect()} == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 5}


def test_triangles_of_many_passes_and_of_any_ids(spark, monkeypatch):
    from crowdlink import triangles as T

    for name, size in (("BLOCK", 16), ("HELD", 32), ("ROW", 8), ("TESTED", 5)):
        monkeypatch.setattr(T, name, size)
    rng = np.random.default_rng(6)
    pairs = [x for x in itertools.combinations(range(24), 2) if rng.random() < 0.35]
    met = set(pairs)
    expected = [t for t in itertools.combinations(range(24), 3) if met >= set(itertools.combinations(t, 2))]
    rows = [(w, u) for u, w in pairs[::2]] + pairs + [(3, 3), (None, 4)]
    for kind, of in (("long", lambda x: x * 1000), ("int", lambda x: x - 7), ("string", lambda x: chr(97 + x)), ("long", lambda x: x << 50)):
        e = spark.createDataFrame([tuple(None if x is None else of(x) for x in r) for r in rows], f"u {kind}, w {kind}")
        assert sorted(tuple(r) for r in T.triangles(e).collect()) == [tuple(map(of, t)) for t in expected]
        assert T.count_triangles(e).first().triangles == len(expected)
    assert T.count_triangles(e.limit(0)).first().triangles == 0 and T.triangles(e.limit(0)).count() == 0


def test_triangles_shuffle_no_pairs_of_neighbours(spark):
    from crowdlink import graph

    written = lambda: sum(int(s.shuffleWriteRecords()) for s in stages())
    store = spark.sparkContext._jsc.sc().statusStore()

    def stages():
        found = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
        return [found.apply(k) for k in range(found.size())]

    whole = spark.range(120).select(F.col("id").alias("u")).join(spark.range(120).select(F.col("id").alias("w")), F.col("u") < F.col("w"))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        before = written()
        assert graph.triangles(whole).count() == 120 * 119 * 118 // 6
        assert written() - before < 50_000
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("seed", [None, 1, 2])
def test_near_copies_are_all_pairs_that_are_similar(spark, tmp_path, seed):
    from crowdlink.sources import workloads

    if seed is None:  # the long text has every shingle of the others, and is like neither
        texts = ["p q r s t u c d e f g", "p q r s t u x", "p q r s t u y", "", "", None, "a b"]
    else:
        rng = np.random.default_rng(seed)
        lines = [" ".join(rng.choice(list("abcdefghijklmnop"), 7)) for _ in range(12)]
        texts = [" ".join(rng.choice(lines, rng.integers(1, 7))) for _ in range(150)]
    spark.createDataFrame([(n, x) for n, x in enumerate(texts)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    sets = [None if x is None else {tuple(x.split()[i : i + 5]) for i in range(max(len(x.split()) - 4, 1))} for x in texts]
    near = [(i, j) for i in range(len(texts)) for j in range(i) if sets[i] and sets[j] and 2 * len(sets[i] & sets[j]) >= len(sets[i] | sets[j])]
    label = kernels.components(len(texts), *np.array(near).T)
    of = {n: str(label[n]) for n in range(len(texts)) if (label == label[n]).sum() > 1}
    assert {r.rid: r.entity for r in workloads.document_gold(spark, str(tmp_path)).collect()} == of


def test_merges_where_few_links_are_positive_equal_greedy(monkeypatch):
    rng = np.random.default_rng(6)
    for k in range(300):
        n = int(rng.integers(2, 60))
        a, b = rng.integers(0, n, (2, 5 * n))
        a, b = a[a != b], b[a != b]
        odds = np.round(rng.normal(-0.5, 2, len(a)), 12) if k % 3 else kernels.log_odds(rng.integers(0, 6, len(a)) / 5)
        whole = None if k % 2 else rng.random(n) < 0.8
        bound = None if k % 4 < 2 else (-1.0, -1, -1)
        assert (kernels.agglomerate_few(n, a, b, odds, whole, bound) == kernels.agglomerate(n, a, b, odds, whole, bound)).all()
    u, w = (x.ravel() for x in np.meshgrid(np.arange(400), np.arange(400)))
    u, w = u[u < w], w[u < w]
    odds = np.where((u % 100 == w % 100) & (rng.random(len(u)) < 0.5), 1.386294361120, -0.405465108108)
    expected, took = kernels.agglomerate_few(400, u, w, odds), []
    few = kernels.agglomerate_few
    monkeypatch.setattr(kernels, "agglomerate_few", lambda *x: took.append(1) or few(*x))
    assert (kernels.agglomerate(400, u, w, odds) == expected).all() and took  # sums of all pairs are not kept
