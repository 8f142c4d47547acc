"""Hand graphs with exact rationals, invariants, criteria."""

from fractions import Fraction as Q

import pytest
from pyspark.sql import functions as F

from walkrank.functions.bounds import tail_factor
from walkrank.operators import baselines, measures
from walkrank.operators.attenuation import Attenuation, attenuation_limits, sigma_max
from walkrank.operators.criteria import FixedLevels, RankingCriterion, ScoreCriterion, TopKCriterion
from walkrank.operators.engine import compare, full_ranking, ladder, level_bounds, rank_nodes, ranked, scores, top_k
from walkrank.operators.graph import Graph, is_complete, is_symmetric
from walkrank.plans import ordered


def graph(spark, edges, nodes=None, undirected=True):
    e = spark.createDataFrame(edges, "src long, dst long") if edges else spark.createDataFrame([], "src long, dst long")
    n = spark.createDataFrame([(x,) for x in nodes], "id long") if nodes is not None else None
    return Graph.from_edges(e, n, undirected=undirected)


PATH, STAR, DAG = [(0, 1), (1, 2), (2, 3)], [(0, 1), (0, 2), (0, 3)], [(0, 1), (0, 2), (1, 2), (2, 3)]
K4 = [(a, b) for a in range(4) for b in range(a)]


def exact_bounds(edges, n, r, undirected):
    arcs = {(a, b) for a, b in edges} | ({(b, a) for a, b in edges} if undirected else set())
    d = max([sum(a == v for a, _ in arcs) for v in range(n)], default=0)
    alpha = Q(1, 1 + d)
    gamma, w, k = d / (1 - alpha * d), [Q(1)] * n, [Q(0)] * n
    for i in range(1, r + 1):
        w = [sum(w[b] for a, b in arcs if a == v) for v in range(n)]
        k = [x + alpha**i * y for x, y in zip(k, w, strict=True)]
    return {v: (k[v] + (alpha ** (r + 1) * w[v] if undirected else 0), k[v] + alpha ** (r + 1) * w[v] * gamma) for v in range(n)}


@pytest.mark.parametrize(("edges", "n", "undirected"), [(PATH, 4, True), (STAR, 4, True), (K4, 4, True), (DAG, 4, False)])
@pytest.mark.parametrize("numeric", ["scaled", "exact", "bigint"])
def test_hand_graphs(spark, edges, n, undirected, numeric):
    g = graph(spark, edges, undirected=undirected)
    for r in (1, 3):
        got = {x.id: (x.floor, x.ceiling) for x in rank_nodes(g, FixedLevels(r), numeric=numeric).frame.collect()}
        want = exact_bounds(edges, n, r, undirected)
        for v in range(n):
            assert got[v] == pytest.approx(tuple(map(float, want[v])), abs=1e-12)


def test_printed_values(spark):
    got = {x.id: (x.floor, x.ceiling) for x in level_bounds(graph(spark, PATH), 3).frame.collect()}
    assert got[0] == pytest.approx((19 / 27, 8 / 9)) and got[1] == pytest.approx((101 / 81, 14 / 9))
    star = graph(spark, STAR)
    assert top_k(star, 1, 0.1).report.levels == 1 and top_k(star, 1, 0.01).report.levels == 3
    assert full_ranking(star, 0.1).report.levels == 4


def test_sharp_on_complete_graphs(spark):
    g = graph(spark, K4)
    assert is_complete(g)
    for r in ladder(g, [FixedLevels(i) for i in (1, 2, 4)]):
        assert {round(x.ceiling, 12) for x in r.frame.collect()} == {3.0}


def test_odd_graphs(spark):
    loop = scores(graph(spark, [(0, 0)]), 1e-6)
    assert loop.scores().first().score == pytest.approx(1.0, abs=1e-5)
    isolated = top_k(graph(spark, PATH, nodes=[0, 1, 2, 3, 9]), 5, 1e-3)
    assert {x.id: x.floor for x in isolated.frame.collect()}[9] == 0.0
    empty = full_ranking(graph(spark, [], nodes=[1, 2]), 1e-3)
    assert empty.report.converged and empty.report.levels == 1 and empty.report.gamma == 0
    none = top_k(graph(spark, []), 3, 1e-3)
    assert none.frame.count() == 0 and none.report.converged
    assert top_k(graph(spark, PATH), 10, 1e-2).report.converged  # more than there are


def test_edges_are_a_set(spark):
    e = spark.createDataFrame([(1, 2), (1, 2), (2, 1), (None, 3), (3, None)], "src long, dst long")
    assert Graph.from_edges(e).edges.count() == 2 and Graph.from_edges(e, undirected=True).edges.count() == 2
    assert Graph.from_edges(e.withColumn("extra", F.lit(1))).nodes.count() == 2
    assert Graph.from_edges(spark.createDataFrame([(1, 1), (1, 2)], "src long, dst long"), drop_loops=True).edges.count() == 1


def test_inbound_is_outbound_of_the_reverse(spark):
    a = level_bounds(graph(spark, DAG, undirected=False).reverse(), 3).frame
    b = level_bounds(graph(spark, [(b, a) for a, b in DAG], undirected=False), 3).frame
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_alpha_limits(spark):
    with pytest.raises(ValueError):
        rank_nodes(graph(spark, PATH), RankingCriterion(1e-3), alpha=0.5)
    with pytest.raises(ValueError):
        tail_factor(0.5, 2)
    with pytest.raises(ValueError):
        TopKCriterion(1, 0.0).check(level_bounds(graph(spark, PATH), 2).frame, 4)
    assert Attenuation.default(2.0).of(3) == pytest.approx(1 / 7)
    assert sigma_max(graph(spark, K4)) == pytest.approx(3.0, abs=1e-5)
    low, high = attenuation_limits(graph(spark, STAR))
    assert low == pytest.approx(1 / 3) and high == pytest.approx(1 / 3**0.5, abs=1e-4)


@pytest.fixture(scope="module")
def heavy(spark, sf):
    from walkrank.workloads.graphs import build

    g = build("part_supplier_heavy", spark, sf)
    return g, baselines.dense_exact(g)


def test_figures_of_a_table_graph(heavy):
    g, exact = heavy
    assert (g.stats.n, g.stats.m, g.stats.d_max) == (204, 1160, 71)
    r = top_k(g, 10, 1e-4)
    assert r.report.levels == 6 and [x - 10 for x in r.report.live] == [194, 192, 0, 0, 0, 0]
    keys = [x.id - (1 << 40) for x in r.ranking(10).orderBy("rank").collect()]
    assert keys == [2, 3, 0, 5, 1, 6, 7, 8, 9, 4]


def test_bounds_hold_and_narrow(spark, heavy):
    g, exact = heavy
    truth = spark.createDataFrame(list(exact.items()), "id long, score double")
    for kind in ("standard", "tight", "ratio"):
        frames = [level_bounds(g, i, bounds=kind).frame for i in (1, 2, 3)]
        assert all(measures.bound_violations(f, truth, 1e-9) == 0 for f in frames)
        assert all(measures.monotone_violations(a, b, 1e-9) == 0 for a, b in zip(frames[:-1], frames[1:], strict=True))
    h = rank_nodes(g, FixedLevels(4), numeric="exact", keep_levels=True).history
    assert all(measures.growth_violations(a, b, g.stats.d_max) == 0 for a, b in zip(h[:-1], h[1:], strict=True))


def test_guarantees_at_the_stop(spark, heavy):
    g, exact = heavy
    truth = spark.createDataFrame(list(exact.items()), "id long, score double")
    eps = 1e-3
    full = full_ranking(g, eps)
    by_floor = full.frame.select("id", F.col("floor").alias("score"))
    assert measures.misranked_pairs(by_floor, truth, eps) == 0
    assert measures.max_abs_error(scores(g, eps).scores(), truth) < eps
    top = top_k(g, 10, eps)
    kept = {x.id for x in top.ranking(10).collect()}
    least = min(exact[x] for x in kept)
    assert all(v <= least + eps for k, v in exact.items() if k not in kept)
    a, b = sorted(exact, key=lambda k: -exact[k])[:2]
    assert compare(g, b, a, 1e-4).report.winner == (a, b)
    assert top_k(g, g.stats.n, eps).report.levels == full.report.levels
    assert [r.report.levels for r in ladder(g, [RankingCriterion(x) for x in (1e-1, eps, 1e-6)])] == [full_ranking(g, x).report.levels for x in (1e-1, eps, 1e-6)]
    short = full_ranking(g, 1e-12, max_levels=2).report
    assert not short.converged and short.levels == 2


def test_order_without_one_partition(heavy):
    g, _ = heavy
    frame = level_bounds(g, 3).frame.cache()
    rows = frame.collect()
    pairs = sum(x.floor > y.ceiling for x in rows for y in rows)
    assert ordered.separated_pairs(frame, 204) == ordered.separated_pairs(frame, 204, 17) == pairs
    for eps in (1e-1, 1e-3, 1e-5):
        line = sorted(rows, key=lambda x: (-x.floor, -x.ceiling, x.id))
        bad = sum(a.floor <= b.ceiling - eps for a, b in zip(line[:-1], line[1:], strict=True))
        assert ordered.adjacent_failures(frame, eps, 204) == ordered.adjacent_failures(frame, eps, 204, 11) == bad
    want = [(i + 1, x.id) for i, x in enumerate(sorted(rows, key=lambda x: (-x.floor, x.id)))]
    for per in (None, 13):
        assert [(x["rank"], x.id) for x in ranked(frame, "floor", per).orderBy("rank").collect()] == want
    large = TopKCriterion(30, 1e-3)
    small = large.check(frame, 204)
    big = large.check_large(frame, 204, 30)
    assert (small.done, small.live, small.bar) == (big.done, big.live, big.bar)


def test_baselines(spark, heavy):
    g, exact = heavy
    truth = spark.createDataFrame(list(exact.items()), "id long, score double")
    cg, tps, fp = baselines.solve_cg(g), baselines.tolerance_partial_sum(g), baselines.solve_fixed_point(g)
    assert cg.converged and measures.max_abs_error(cg.scores, truth) < 1e-10
    assert measures.max_abs_error(tps.scores, truth) < 1e-7 and measures.max_abs_error(fp.scores, truth) < 1e-9
    partial = level_bounds(g, tps.levels).state.select("id", F.col("k").alias("score"))
    assert measures.max_abs_error(tps.scores, partial) == 0
    directed = graph(spark, DAG, undirected=False)
    assert not is_symmetric(directed.edges)
    with pytest.raises(ValueError):
        baselines.solve_cg(directed)
    got = {x.id: x.score for x in baselines.solve_fixed_point(directed).scores.collect()}
    assert got == pytest.approx({0: 25 / 27, 1: 4 / 9, 2: 1 / 3, 3: 0.0})


def test_counts_that_do_not_fit(spark):
    with pytest.raises(OverflowError):
        rank_nodes(graph(spark, [(a, b) for a in range(9) for b in range(a)]), FixedLevels(30), numeric="bigint")


def test_misranked_pairs_by_brute_force(spark):
    import random

    rng = random.Random(1)
    a = {i: rng.randrange(12) / 10 for i in range(60)}
    b = {i: rng.randrange(12) / 10 for i in range(60)}
    x, y = (spark.createDataFrame(list(d.items()), "id long, score double") for d in (a, b))
    for eps in (0.0, 0.25):
        want = sum((a[i] - a[j] >= eps if eps else a[i] > a[j]) and b[i] < b[j] for i in a for j in a)
        assert measures.misranked_pairs(y, x, eps) == measures.misranked_pairs(y, x, eps, 9) == want


def test_several_k_at_once(spark):
    """Each k stops where a run of its own stops, with the same live sets."""
    from walkrank.operators.engine import top_k, top_k_sweep

    g = graph(spark, [(0, x) for x in range(1, 9)] + [(1, x) for x in range(9, 12)] + [(2, 3)])
    found = top_k_sweep(g, [1, 3, 50], 1e-2)
    for k, report in found.items():
        own = top_k(g, k, 1e-2).report
        assert (report.levels, report.live, report.converged) == (own.levels, own.live, own.converged), k


def test_orders_by_ranges(spark):
    """Numbers, next rows and wrongly ordered pairs in ranges of a few rows against plain sorting."""
    import random

    from pyspark.sql import functions as F

    from walkrank.operators import measures
    from walkrank.plans import ordered

    rng = random.Random(1)
    rows = [(i, round(rng.choice([rng.random(), 0.5, 0.25]), 2), round(rng.random(), 1)) for i in range(150)]
    df = spark.createDataFrame(rows, "id long, score double, other double")
    got = {r.id: r.rank for r in ordered.numbered(df, "score", 7).collect()}
    assert [got[i] for i, _, _ in sorted(rows, key=lambda r: (-r[1], r[0]))] == list(range(1, 151))
    after = {r.id: r.next for r in ordered.followed(df, ["score", "id"], "id", "next", 11).collect()}
    line = [i for i, _, _ in sorted(rows, key=lambda r: (r[1], r[0]))]
    assert after == dict(zip(line, [*line[1:], None], strict=True))
    cuts = sorted({r[1] for r in rows})[::3]
    parts = {r.id: r.p for r in df.select("id", ordered.range_of("score", cuts).alias("p")).collect()}
    assert parts == {i: sum(c >= s for c in cuts) for i, s, _ in rows}
    exact = df.select("id", F.col("other").alias("score"))
    for eps in (0.0, 0.2):
        ahead = lambda x, y: x - y > 1e-9 if not eps else x >= y + eps
        want = sum(ahead(a[2], b[2]) and a[1] < b[1] for a in rows for b in rows)
        assert measures.misranked_pairs(df.select("id", "score"), exact, eps, 9) == want
    ties = measures.near_ties(df.select("id", "score"), 0.011).collect()
    classes = {}
    for i, s, _ in rows:
        classes.setdefault(s, []).append(i)
    want = {(*sorted((min(x), min(y))),) for a, x in classes.items() for b, y in classes.items() if abs(a - b) < 0.011 and (a != b or len(x) > 1)}
    assert {(r.low, r.high) for r in ties} == want


def test_layout_is_shared(spark, sf, monkeypatch):
    """Edges are told apart once, loops and both ways, and other partitions come from the tables that are there."""
    from walkrank.operators.graph import Graph
    from walkrank.plans import layout

    pairs = [(1, 2), (2, 1), (3, 3), (3, 3), (2, 3)]
    g = Graph.from_edges(spark.createDataFrame(pairs, "src long, dst long"), spark.createDataFrame([(9,), (1,)], "id long"), undirected=True)
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 1), (2, 3), (3, 2), (3, 3)]
    assert sorted(r.id for r in g.nodes.collect()) == sorted(r.id for r in g.placed.nodes.collect()) == [1, 2, 3, 9]
    assert g.as_undirected() is g
    fresh = Graph(g.edges, g.nodes, True)
    fresh.dealt(2)
    assert "placed" not in vars(fresh)  # not laid out itself
    monkeypatch.setattr(layout, "written", None)  # nothing more is written
    for parts in (1, 3):
        other = g.dealt(parts)
        assert (other.placed.parts, other.placed.large) == (parts, True) and other.stats == g.stats
        assert rank_nodes(other, FixedLevels(3)).frame.orderBy("id").collect() == rank_nodes(g, FixedLevels(3)).frame.orderBy("id").collect()


def test_ladder_of_several_criteria(spark):
    """One run gives each k, the ranking and the partial sum the levels of runs of their own, and the same live sets at the end."""
    from walkrank.operators.baselines import tolerance_partial_sum
    from walkrank.operators.criteria import TopKCriterion
    from walkrank.operators.engine import LastTerm

    g = graph(spark, [(0, x) for x in range(1, 9)] + [(1, x) for x in range(9, 12)] + [(2, 3), (3, 4)])
    for eps, tol in ((1e-2, 1e-9), (1e-6, 1e-1)):
        steps, term = [*(TopKCriterion(k, eps) for k in (1, 3, 5, 50)), RankingCriterion(eps)], LastTerm(tol)
        for step, r in zip(steps, ladder(g, steps, term=term), strict=True):
            own = rank_nodes(g, step)
            assert (r.report.levels, r.report.converged, r.report.bar) == (own.report.levels, own.report.converged, own.report.bar)
            assert r.frame.where("live").count() == own.frame.where("live").count()
        alone = tolerance_partial_sum(g, tol)
        assert (term.levels, term.converged) == (alone.levels, alone.converged) and 0 < term.own <= term.seconds


def test_sweep_runs_its_levels_once(spark, sf, monkeypatch):
    """Five k and the full ranking of one graph: as many levels as the strictest needs, and those of the solve."""
    from walkrank.operators import levels
    from walkrank.workloads import experiments

    made, one = [], levels.advance_level
    monkeypatch.setattr(levels, "advance_level", lambda *a: made.append(1) or one(*a))
    rows = {r.method: r for r in experiments.topk_sweep(spark, sf, ("part_supplier_heavy",), (10, 1, 5), 1e-3).collect()}
    assert set(rows) == {"top 1", "top 5", "top 10", "full", "linear solve 0.0001"}
    assert len(made) == rows["full"].levels and rows["top 1"].levels <= rows["top 5"].levels <= rows["top 10"].levels <= rows["full"].levels
    made.clear()
    rows = {r.method: r for r in experiments.epsilon_sweep(spark, sf, grid=(1e-1, 1e-3)).collect()}
    assert len(made) == max(rows["eps 0.001"].levels, rows["partial sum 1e-09"].levels)


def test_insertions_measure_their_graph_once(spark, sf, monkeypatch):
    """All batches of insertions lead to one graph: one new state and one static run for all sizes, and one for each size of deletions."""
    from walkrank.workloads import experiments

    begun, static = [], []
    start, rank = experiments.dynamic.start, experiments.rank_nodes
    monkeypatch.setattr(experiments.dynamic, "start", lambda *a: begun.append(1) or start(*a))
    monkeypatch.setattr(experiments, "rank_nodes", lambda *a: static.append(1) or rank(*a))
    for inserts, starts, runs in ((True, 1, 1), (False, 3, 2)):
        begun.clear(), static.clear()
        rows = experiments.batch_sweep(spark, sf, ("part_supplier_heavy",), (1, 4), 3, 1e-1, inserts).collect()
        assert sorted(r.batch for r in rows) == [1, 4] and (len(begun), len(static)) == (starts, runs)
        assert all(r.restored is (True if inserts else None) for r in rows)
