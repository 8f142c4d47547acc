"""Registered queries of the engine and their SQL."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.ids import pack, sql_pack
from ..operators import baselines, dynamic, measures
from ..operators.attenuation import sigma_max
from ..operators.criteria import FixedLevels, RankingCriterion, TopKCriterion
from ..operators.engine import LastTerm, compare, full_ranking, ladder, level_bounds, rank_nodes, ranked, report_metrics, scores, top_k, top_k_sweep
from ..operators.graph import Graph, is_complete, out_degrees
from ..plans import ordered
from ..sources.tables import table
from . import oracle as O
from .graphs import EDGES_SQL, NODES_SQL, build, follow_rows, part_supplier_heavy

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def register(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return register


def rows(spark: SparkSession, data: list, schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)


HEAVY = "part_supplier_heavy"

# graphs: arcs of each


_GRAPH_NAMES = {"document_line": "q_document_line_graph", "embedding_sim": "q_embedding_sim_graph", "part_copurchase": "q_graph_copurchase", "page_link": "q_page_links", "user_follow": "q_user_follow_graph", "user_hour_event": "q_user_hour_graph"}


def register_graph(graph: str) -> None:
    def q(spark: SparkSession, sf_dir: str) -> DataFrame:
        return build(graph, spark, sf_dir).edges

    def nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
        return build(graph, spark, sf_dir).nodes

    query(EDGES_SQL[graph], _GRAPH_NAMES.get(graph, f"q_graph_{graph}"))(q)
    if graph in ("document_line", "page_link", "benchmark_doc_token"):
        query(f"with e as ({EDGES_SQL[graph]}) select distinct id from ({NODES_SQL[graph]})", f"q_nodes_{graph}")(nodes)


for _graph in EDGES_SQL:
    register_graph(_graph)

# model and parameters


@query(f"with e as ({EDGES_SQL['part_supplier']}) select src as id, count(*)::bigint as deg from e group by src")
def q_out_degree(spark, sf_dir):
    return out_degrees(build("part_supplier", spark, sf_dir))


@query(f"with recursive {O.graph_ctes('part_supplier')} select (select count(*) from nd)::bigint as n, (select count(*) from e)::bigint as m, d_max::bigint as d_max, round(alpha, 12) as alpha, round(gamma, 6) as gamma from p")
def q_dmax_alpha_gamma(spark, sf_dir):
    report, stats = (g := build("part_supplier", spark, sf_dir)) and level_bounds(g, 1).report, g.stats
    return rows(spark, [(stats.n, stats.m, stats.d_max, round(report.alpha, 12), round(report.gamma, 6))], "n long, m long, d_max long, alpha double, gamma double")


SIGMA_STEPS = 60


@query(f"""with recursive {O.graph_ctes('part_supplier')},
s as (select 0 as i, id, 1.0::double as x, 1.0::double as norm from nd union all
  select i + 1, id, x / norm, norm from (select i, id, x, sqrt(sum(x * x) over ()) as norm from (select s.i, e.src as id, sum(s.x) as x from s join e on e.dst = s.id where s.i < {SIGMA_STEPS} group by s.i, e.src)))
select round(max(norm), 3) as sigma from s where i = {SIGMA_STEPS}""")
def q_sigma_max(spark, sf_dir):
    return rows(spark, [(round(sigma_max(build("part_supplier", spark, sf_dir), 1e-12, SIGMA_STEPS // 2), 3),)], "sigma double")


# levels and bounds


@query(f"with recursive {O.graph_ctes('part_supplier')}, {O.exact(3)} select id, (max(w) filter (where i = 1))::bigint as w1, (max(w) filter (where i = 2))::bigint as w2, (max(w) filter (where i = 3))::bigint as w3 from x group by id")
def q_walk_counts_l3(spark, sf_dir):
    found = rank_nodes(build("part_supplier", spark, sf_dir), FixedLevels(3), numeric="exact", keep_levels=True).history
    out = found[0].select("id", F.col("w").cast("long").alias("w1"))
    for i in (2, 3):
        out = out.join(found[i - 1].select("id", F.col("w").cast("long").alias(f"w{i}")), "id")
    return out


def rounded(frame: DataFrame) -> DataFrame:
    return frame.select("id", F.round("floor", 8).alias("floor"), F.round("ceiling", 8).alias("ceiling"))


ROUNDED = "select id, round(floor, 8) as floor, round(ceiling, 8) as ceiling from f where i = 4"


@query(f"{O.frames('user_follow', 4)} {ROUNDED}")
def q_bounds_directed_l4(spark, sf_dir):
    return rounded(level_bounds(build("user_follow", spark, sf_dir), 4).frame)


@query(f"{O.frames('part_supplier', 4)} {ROUNDED}")
def q_bounds_undirected_l4(spark, sf_dir):
    return rounded(level_bounds(build("part_supplier", spark, sf_dir), 4).frame)


@query(f"{O.frames('page_link', 4, inbound=True)} {ROUNDED}")
def q_bounds_inbound_l4(spark, sf_dir):
    return rounded(level_bounds(build("page_link", spark, sf_dir).reverse(), 4).frame)


@query(f"with recursive {O.graph_ctes('nation_trade')}, {O.scaled(5)}, {O.bounds(False)} select i::int as level, round(max(abs(ceiling - 25)), 6) as max_gap from f where i <= 5 group by i")
def q_complete_graph_sharp(spark, sf_dir):
    graph = build("nation_trade", spark, sf_dir)
    steps = ladder(graph, [FixedLevels(i) for i in range(1, 6)])
    found = [(i, round(r.frame.agg(F.max(F.abs(F.col("ceiling") - 25))).first()[0], 6)) for i, r in enumerate(steps, 1)]
    return rows(spark, found, "level int, max_gap double")


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(4)} select id, round(k + s * alpha / (1 - alpha), 8) as floor, round(k + alpha * gamma * s, 8) as ceiling from g, p where i = 4")
def q_bounds_tight_l4(spark, sf_dir):
    return rounded(level_bounds(build(HEAVY, spark, sf_dir), 4, bounds="tight").frame)


@query(f"""{O.frames('part_copurchase', 4)}, r as (select min(a.s / b.s) as low, max(a.s / b.s) as high from g a join g b on a.id = b.id where a.i = 4 and b.i = 3 and b.s > 0)
select f.id, round(greatest(floor, k + s * low / (1 - low)), 8) as floor, round(least(ceiling, k + s * high / (1 - high)), 8) as ceiling from f join g on f.id = g.id and f.i = g.i, r where f.i = 4""")
def q_bounds_ratio_l4(spark, sf_dir):
    return rounded(level_bounds(build("part_copurchase", spark, sf_dir), 4, bounds="ratio").frame)


@query(f"""with recursive {O.graph_ctes(HEAVY)}, {O.scaled(5)}, {O.bounds(True)}, {O.exact(5)}
select 'levels' as check_name, (select count(*) from f a join f b on a.id = b.id and b.i = a.i + 1 where a.i >= 2 and (b.floor < a.floor - 1e-12 or b.ceiling > a.ceiling + 1e-12))::bigint as violations
union all select 'growth', (select count(*) from x a join x b on a.id = b.id and b.i = a.i + 1, p where a.i >= 1 and b.w > a.w * p.d_max)::bigint""")
def q_level_invariants(spark, sf_dir):
    """Floors never fall, ceilings never rise; counts never grow by more than the largest degree."""
    graph = build(HEAVY, spark, sf_dir)
    found = rank_nodes(graph, FixedLevels(5), numeric="exact", keep_levels=True)
    growth = sum(measures.growth_violations(a, b, graph.stats.d_max) for a, b in zip(found.history[:-1], found.history[1:], strict=True))
    frames = [r.frame for r in ladder(graph, [FixedLevels(i) for i in (2, 3, 4, 5)])]
    moved = sum(measures.monotone_violations(a, b) for a, b in zip(frames[:-1], frames[1:], strict=True))
    return rows(spark, [("levels", moved), ("growth", growth)], "check_name string, violations long")


# criteria


@query(f"{O.frames(HEAVY, 16)}, {O.topk(10, 1e-6)} select rn::bigint as rank, id from t where i = {O.LAST}")
def q_topk_converged(spark, sf_dir):
    return top_k(build(HEAVY, spark, sf_dir), 10, 1e-6).ranking(10).select("rank", "id")


@query(f"{O.frames('customer_supplier', 24)}, {O.ranking(1e-9)} select (row_number() over (order by round(floor, 10) desc, id))::bigint as rank, id from f where i = {O.LAST}")
def q_full_ranking_eps(spark, sf_dir):
    frame = full_ranking(build("customer_supplier", spark, sf_dir), 1e-9).frame
    return ranked(frame.select("id", F.round("floor", 10).alias("floor"))).select("rank", "id")


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)} select id, round(k, 6) as score from g where i = 80")
def q_scores_eps(spark, sf_dir):
    return scores(build(HEAVY, spark, sf_dir), 1e-10).scores().select("id", F.round("score", 6).alias("score"))


PAIR = (1099511627776 + 15, 1099511627776 + 18)


@query(f"""{O.frames(HEAVY, 20)}, b as (select a.i, a.id as x, b.id as y, a.floor > b.ceiling - 1e-6 as ok, a.floor as fa from f a join f b on a.i = b.i where a.id in {PAIR} and b.id in {PAIR} and a.id <> b.id)
select x as ahead, y as behind, i::int as level from b where ok order by i, fa desc, x limit 1""")
def q_pair_compare(spark, sf_dir):
    report = compare(build(HEAVY, spark, sf_dir), *PAIR, 1e-6).report
    return rows(spark, [(*report.winner, report.levels)], "ahead long, behind long, level int")


@query(f"{O.frames(HEAVY, 12)}, {O.topk(10, 1e-4)} select i::int as level, live::bigint as live from v where i <= {O.LAST}")
def q_live_set_by_level(spark, sf_dir):
    live = top_k(build(HEAVY, spark, sf_dir), 10, 1e-4).report.live
    return rows(spark, list(enumerate(live, 1)), "level int, live long")


@query(f"""{O.frames(HEAVY, 12)}, {O.topk(10, 1e-4)}, m as (select 'd_max' as name, max(d_max)::double as value from p union all select 'levels', {O.LAST} union all select 'live', (select live from v where i = {O.LAST}))
select name, value::double as value from m""")
def q_run_metrics(spark, sf_dir):
    """The figures of a run as a map, without those that are zero or not whole."""
    metrics = report_metrics(spark, top_k(build(HEAVY, spark, sf_dir), 10, 1e-4).report)
    whole = metrics.select(F.explode(F.map_filter("metrics", lambda _, v: v == F.floor(v))).alias("name", "value"))
    return whole


SEPARATED = "(select count(*) from f a join f b on a.i = b.i and a.floor > b.ceiling where a.i = {level})"


@query(f"{O.frames(HEAVY, 12)}, {O.ranking(1e-3)}, c as (select {O.LAST} as i, {SEPARATED.format(level=O.LAST)}::bigint as separated, (select count(*) from nd) as n) select i::int as level, separated, (n * (n - 1) // 2)::bigint as pairs, round(separated / (n * (n - 1) // 2), 10) as fraction from c")
def q_separated_fraction(spark, sf_dir):
    found = full_ranking(g := build(HEAVY, spark, sf_dir), 1e-3)
    some, pairs, share = measures.separated_fraction(found.frame, g.stats.n)
    return rows(spark, [(found.report.levels, some, pairs, round(share, 10))], "level int, separated long, pairs long, fraction double")


@query(f"{O.frames('user_follow', 40)} select {SEPARATED.format(level=40)}::bigint as separated, (select count(*) * (count(*) - 1) // 2 from nd)::bigint as pairs")
def q_separated_pairs_bruteforce(spark, sf_dir):
    """The theta join that the sorted count replaces; the graph has one node for each user."""
    frame = level_bounds(build("user_follow", spark, sf_dir), 40).frame
    some = frame.alias("a").join(frame.alias("b"), F.col("a.floor") > F.col("b.ceiling")).count()
    n = frame.count()
    return rows(spark, [(some, n * (n - 1) // 2)], "separated long, pairs long")


EPS_GRID = tuple(10.0**-i for i in range(1, 13))


@query(f"{O.frames(HEAVY, 26)}, grid as (select unnest({list(EPS_GRID)}) as eps), bad as (select i, ceiling, lag(floor) over (partition by i order by floor desc, ceiling desc, id) as prev from f), v as (select eps, i from bad, grid group by eps, i having count(*) filter (where prev <= ceiling - eps) = 0), l as (select eps, min(i) as i from v group by eps), sep as (select a.i, count(*) as c from f a join f b on a.i = b.i and a.floor > b.ceiling where a.i in (select i from l) group by a.i) select eps, l.i::int as level, round(coalesce(c, 0) / (select count(*) * (count(*) - 1) // 2 from nd), 8) as fraction from l left join sep on sep.i = l.i")
def q_epsilon_sweep(spark, sf_dir):
    graph, found = build(HEAVY, spark, sf_dir), []
    for eps, r in zip(EPS_GRID, ladder(graph, [RankingCriterion(eps) for eps in EPS_GRID]), strict=True):
        found.append((eps, r.report.levels, round(measures.separated_fraction(r.frame, graph.stats.n)[2], 8)))
    return rows(spark, found, "eps double, level int, fraction double")


K_GRID = (1, 10, 100, 1000)


def _sweep_sql() -> str:
    one = "select {k}::bigint as k, min(i)::int as level from (with {criterion} select * from v) where done"
    return f"{O.frames(HEAVY, 16)} " + " union all ".join(one.format(k=k, criterion=O.topk(k, 1e-4)) for k in K_GRID)


@query(_sweep_sql())
def q_topk_sweep(spark, sf_dir):
    found = top_k_sweep(build(HEAVY, spark, sf_dir), list(K_GRID), 1e-4)
    return rows(spark, [(k, r.levels) for k, r in found.items()], "k long, level int")


@query(f"{O.frames(HEAVY, 12)}, {O.topk(500, 1e-3)} select live::bigint as live, done from v where i = 12")
def q_topk_beyond_driver(spark, sf_dir):
    """The top-k criterion as it runs where k is too large for the driver."""
    graph = build(HEAVY, spark, sf_dir)
    frame = level_bounds(graph, 12).frame
    verdict = TopKCriterion(500, 1e-3).check_large(frame, graph.stats.n, min(500, graph.stats.n))
    return rows(spark, [(verdict.live, verdict.done)], "live long, done boolean")


INSTANCES = ("part_supplier", "part_supplier_heavy", "customer_supplier", "order_tree", "user_hour_event")
INSTANCE_EPS = (1e-1, 1e-3, 1e-5)


def _instances_sql() -> str:
    one = "select '{name}' as graph, {eps!r}::double as eps, (select min(i) from (with {criterion} select * from v) where done)::int as level from p"
    graphs = []
    for name in INSTANCES:
        each = [one.format(name=name, eps=eps, criterion=O.ranking(eps)) for eps in INSTANCE_EPS]
        each.append(f"select '{name}', 0.0::double, (select min(i) from (select i, max(s) as s from g group by i) where s < 1e-9)::int from p")
        graphs.append(f"select * from ({O.frames(name, 30)} {' union all '.join(each)})")
    return " union all ".join(graphs)


@query(_instances_sql())
def q_instance_levels(spark, sf_dir):
    """Levels of the ranking for each graph and eps, and of the partial sum to 1e-9 (as eps 0)."""
    found = []
    for name in INSTANCES:
        graph = build(name, spark, sf_dir)
        term = LastTerm(1e-9)
        found += [(name, eps, r.report.levels) for eps, r in zip(INSTANCE_EPS, ladder(graph, [RankingCriterion(eps) for eps in INSTANCE_EPS], term=term), strict=True)]
        found.append((name, 0.0, term.levels))
        graph.placed.release()
    return rows(spark, found, "graph string, eps double, level int")


@query(f"{O.frames(HEAVY, 6)} select id, round(floor, 8) as floor, round(ceiling, 8) as ceiling from f where i = 6")
def q_bounds_large_layout(spark, sf_dir):
    """Bounds from the layout of large graphs: edges and states dealt alike, edges to hubs apart."""
    graph = build(HEAVY, spark, sf_dir)
    return rounded(level_bounds(Graph(graph.edges, graph.nodes, True, 6), 6).frame)


@query(f"{O.frames(HEAVY, 16)}, {O.topk(50, 1e-5)} select rn::bigint as rank, id from t where i = {O.LAST}")
def q_topk_large_layout(spark, sf_dir):
    graph = build(HEAVY, spark, sf_dir)
    return top_k(Graph(graph.edges, graph.nodes, True, 6), 50, 1e-5).ranking(50).select("rank", "id")


# baselines


@query(f"with recursive {O.graph_ctes('part_supplier')}, {O.scaled(24)}, stop as (select min(i) as i from (select i, max(s) as s from g group by i) where s < 1e-9) select g.i::int as level, id, round(k, 8) as score from g, stop where g.i = stop.i")
def q_tps_baseline(spark, sf_dir):
    found = baselines.tolerance_partial_sum(build("part_supplier", spark, sf_dir), 1e-9)
    return found.scores.select(F.lit(found.levels).alias("level"), "id", F.round("score", 8).alias("score"))


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)} select id, round(k, 8) as score from g where i = 80")
def q_cg_scores(spark, sf_dir):
    return baselines.solve_cg(build(HEAVY, spark, sf_dir)).scores.select("id", F.round("score", 8).alias("score"))


#: The loose solve in SQL: conjugate gradients, a step a round, until the residual is below 1e-4 of the right side.
_LOOSE = """cg as (select 0 as i, id, 0.0::double as x, 1.0::double as r, 1.0::double as d, count(*) over ()::double as rr, count(*) over ()::double as n from nd union all
  select i + 1, id, x + a * d, r - a * q, (r - a * q) + next / rr * d, next, n from (select *, sum((r - a * q) * (r - a * q)) over () as next from (
    select *, rr / sum(d * q) over () as a from (select c.*, c.d - p.alpha * coalesce(s.w, 0) as q from cg c join p on true left join (select e.src, sum(t.d) as w from cg t join e on e.dst = t.id group by e.src) s on s.src = c.id
      where c.rr / c.n >= 1e-8 and c.i < 60)))),
sol as (select id, x from cg where i = (select max(i) from cg)),
score as (select nd.id, p.alpha * coalesce(sum(sol.x), 0) as score from nd join p on true left join e on e.src = nd.id left join sol on sol.id = e.dst group by nd.id, p.alpha)"""


@query(f"""with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)}, {_LOOSE},
loose as (select id from score order by score desc, id limit 100), tight as (select id from g where i = 80 order by k desc, id limit 100)
select 100::bigint as k, count(*) >= 90 as mostly_right from loose join tight using (id)""")
def q_cg_loose_top100(spark, sf_dir):
    """The hundred best of a loose solve against those of a tight one: nine in ten at least are the same."""
    graph = build(HEAVY, spark, sf_dir)
    loose, tight = baselines.solve_cg(graph, 1e-4).top(100), baselines.solve_cg(graph).top(100)
    return rows(spark, [(100, measures.topk_overlap(loose, tight) >= 90)], "k long, mostly_right boolean")


@query(f"with recursive {O.graph_ctes('user_follow')}, {O.scaled(2600)} select id, round(k, 6) as score from g where i = 2600")
def q_fixed_point_directed(spark, sf_dir):
    return baselines.solve_fixed_point(build("user_follow", spark, sf_dir), 1e-10).scores.select("id", F.round("score", 6).alias("score"))


@query(f"with e as ({EDGES_SQL[HEAVY]}) select (row_number() over (order by deg desc, id))::bigint as rank, id, deg from (select src as id, count(*)::bigint as deg from e group by src)")
def q_degree_rank(spark, sf_dir):
    return baselines.degree_rank(build(HEAVY, spark, sf_dir))


@query(f"with recursive {O.graph_ctes('nation_trade')}, {O.scaled(700)} select id, round(k, 6) as score from g where i = 700")
def q_dense_exact(spark, sf_dir):
    found = baselines.dense_exact(build("nation_trade", spark, sf_dir))
    return rows(spark, [(k, round(v, 6)) for k, v in sorted(found.items())], "id long, score double")


# accuracy


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)}, r as (select round(k, 9) as score, count(*) as c from g where i = 80 group by 1) select sum(c * (c - 1) // 2)::bigint as tied from r")
def q_tied_pairs(spark, sf_dir):
    solved = baselines.solve_cg(build(HEAVY, spark, sf_dir)).scores
    return rows(spark, [(measures.tied_pairs(solved, 9),)], "tied long")


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)}, {O.bounds(True)}, z as (select id, k from g where i = 80), a as (select id, floor from f where i = 2) select (select count(*) from z x join z y on x.k > y.k + 1e-9 join a p on p.id = x.id join a q on q.id = y.id where p.floor < q.floor - 1e-12)::bigint as misranked")
def q_misranked_pairs(spark, sf_dir):
    """Pairs that two levels order wrongly."""
    graph = build(HEAVY, spark, sf_dir)
    early = level_bounds(graph, 2).frame.select("id", F.round("floor", 12).alias("score"))
    exact = baselines.solve_cg(graph).scores
    return rows(spark, [(measures.misranked_pairs(early, exact, 1e-9),)], "misranked long")


@query(f"""with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)}, z as (select min(id) as id, count(*) as c, s from (select id, round(k, 8) as s from g where i = 80) group by s)
select a.id as low, b.id as high, a.c::bigint as low_nodes, b.c::bigint as high_nodes from z a join z b on a.id <= b.id and abs(a.s - b.s) < 1e-5 and (a.id <> b.id or a.c > 1)""")
def q_near_tie_pairs(spark, sf_dir):
    solved = baselines.solve_cg(build(HEAVY, spark, sf_dir)).scores
    return measures.near_ties(solved.select("id", F.round("score", 8).alias("score")), 1e-5)


@query(f"{O.frames(HEAVY, 80)} select round(max(abs(a.floor - z.k)), 8) as max_error, count(*) filter (where z.k < a.floor - 1e-12 or z.k > a.ceiling + 1e-12)::bigint as violations from f a join g z on a.id = z.id and z.i = 80 where a.i = 4")
def q_bounds_hold_exact(spark, sf_dir):
    graph = build(HEAVY, spark, sf_dir)
    frame, exact = level_bounds(graph, 4).frame, baselines.solve_cg(graph).scores
    error = measures.max_abs_error(frame.select("id", F.col("floor").alias("score")), exact)
    return rows(spark, [(round(error, 8), measures.bound_violations(frame, exact))], "max_error double, violations long")


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)}, t as (select id from g where i = 80 order by k desc, id limit 50), d as (select id from (select src as id, count(*) as c from e group by src) order by c desc, id limit 50) select count(*)::bigint as shared from t join d using (id)")
def q_topk_overlap(spark, sf_dir):
    graph = build(HEAVY, spark, sf_dir)
    by_degree = out_degrees(graph).orderBy(F.desc("deg"), "id").limit(50)
    return rows(spark, [(measures.topk_overlap(baselines.solve_cg(graph).top(50), by_degree),)], "shared long")


_GEO = ("part_supplier_heavy", "order_tree")


def _geo_sql() -> str:
    parts = []
    for g in _GEO:
        parts.append(f"select (select count(*) from (with recursive {O.graph_ctes(g)}, {O.scaled(3)}, {O.bounds(True)} select 1 from f a join f b on a.floor > b.ceiling and a.i = 3 and b.i = 3)) / ((select count(*) from (with e as ({EDGES_SQL[g]}) {NODES_SQL[g]})) * ((select count(*) from (with e as ({EDGES_SQL[g]}) {NODES_SQL[g]})) - 1) // 2) as share")
    return f"select round(exp(avg(ln(share))), 8) as geo_mean from ({' union all '.join(parts)})"


@query(_geo_sql())
def q_geo_mean_separation(spark, sf_dir):
    shares = []
    for name in _GEO:
        graph = build(name, spark, sf_dir)
        shares.append((measures.separated_fraction(level_bounds(graph, 3).frame, graph.stats.n)[2],))
    return rows(spark, shares, "share double").agg(F.round(measures.geo_mean("share"), 8).alias("geo_mean"))


# dynamic graphs


def removed_sql(graph: str, count: int) -> str:
    return f"select src, dst from e0 except ({O.chosen_sql(graph, count)})"


def after_deletion(spark, sf_dir, graph: str, count: int, criterion, cap: float | None = None):
    start = dynamic.start(build(graph, spark, sf_dir), criterion)
    if cap is not None:
        start.cap = cap
    gone = dynamic.chosen_edges(start.graph.edges, count, start.graph.undirected)
    return start, gone, dynamic.apply_batch(start, dynamic.EdgeBatch.of(deletes=gone))


@query(f"with recursive {O.graph_ctes(HEAVY, edges=removed_sql(HEAVY, 100))}, {O.exact(5)} select id, w::bigint as w5 from x where i = 5")
def q_delete_batch_state(spark, sf_dir):
    return after_deletion(spark, sf_dir, HEAVY, 100, FixedLevels(5))[2].levels[5].select("id", F.col("w").cast("long").alias("w5"))


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.exact(5)} select id, w::bigint as w5 from x where i = 5")
def q_insert_batch_state(spark, sf_dir):
    """The edges go first and then come back in a batch."""
    _, gone, state = after_deletion(spark, sf_dir, HEAVY, 100, FixedLevels(5))
    return dynamic.apply_batch(state, dynamic.EdgeBatch.of(inserts=gone)).levels[5].select("id", F.col("w").cast("long").alias("w5"))


_ALPHA0 = "(select 1.0::double / (1 + max(c)) from (select count(*) as c from e0 group by src))"


@query(f"{O.frames(HEAVY, 20, edges=removed_sql(HEAVY, 100), alpha=_ALPHA0)}, {O.topk(10, 1e-6)} select rn::bigint as rank, id from t where i = (select max(i) from v where done)")
def q_update_topk(spark, sf_dir):
    state = after_deletion(spark, sf_dir, HEAVY, 100, TopKCriterion(10, 1e-6))[2]
    return state.result().ranking(10).select("rank", "id")


_HUB = "select src from e0 group by src order by count(*) desc, src limit 1"


@query(f"{O.frames(HEAVY, 5, edges=f'select src, dst from e0 where src not in ({_HUB}) and dst not in ({_HUB})', alpha=_ALPHA0)} select id, round(floor, 8) as floor, round(ceiling, 8) as ceiling from f where i = 5")
def q_update_gamma_refresh(spark, sf_dir):
    """The hub loses all its edges: the largest degree falls, and with it all ceilings."""
    graph = build(HEAVY, spark, sf_dir)
    start = dynamic.start(graph, FixedLevels(5))
    hub = out_degrees(graph).orderBy(F.desc("deg"), "id").first().id
    return rounded(dynamic.apply_batch(start, dynamic.EdgeBatch.of(deletes=graph.edges.where(F.col("src") == hub))).frame)


@query(f"""with recursive {O.graph_ctes('order_tree', edges=removed_sql('order_tree', 10))}, {O.exact(4)},
ys as (select 0 as i, id, 1::hugeint as w from nd union all select ys.i + 1, e0.src, sum(ys.w)::hugeint from ys join e0 on e0.dst = ys.id where ys.i < 4 group by ys.i, e0.src),
d as (select x.i, x.id from x left join ys on ys.i = x.i and ys.id = x.id where x.i > 0 and x.w <> coalesce(ys.w, 0))
select l.i::int as level, (select count(*) from d where d.i = l.i)::bigint as changed from (select unnest(range(1, 5)) as i) l""")
def q_frontier_sizes(spark, sf_dir):
    frontier = after_deletion(spark, sf_dir, "order_tree", 10, FixedLevels(4))[2].frontier
    return rows(spark, list(enumerate(frontier, 1)), "level int, changed long")


@query(f"""with recursive {O.graph_ctes(HEAVY, edges=removed_sql(HEAVY, 100))}, {O.exact(4)}, b as (select id from x where i = 4)
select distinct src, dst from e""", "q_update_edges")
def q_update_edges(spark, sf_dir):
    return after_deletion(spark, sf_dir, HEAVY, 100, FixedLevels(1))[2].graph.edges.select("src", "dst")


@query(f"""with recursive {O.graph_ctes(HEAVY, edges=removed_sql(HEAVY, 100), alpha=_ALPHA0)}, {O.scaled(9)}, {O.bounds(True)},
a0 as (select {_ALPHA0} as alpha, (select max(c) from (select count(*) as c from e0 group by src)) as d),
w2 as (select 0 as i, id, 1.0::double as s from nd union all select w2.i + 1, e0.src, sum(w2.s) * max(a0.alpha) from w2 join e0 on e0.dst = w2.id, a0 where w2.i < 9 group by w2.i, e0.src),
g2 as (select nd.id, l.i, coalesce(w2.s, 0.0) as s, sum(coalesce(w2.s, 0.0)) over (partition by nd.id order by l.i) as k from nd cross join (select unnest(range(1, 10)) as i) l left join w2 on w2.i = l.i and w2.id = nd.id),
f2 as (select i, id, k + alpha * s as floor, k + alpha * d / (1 - alpha * d) * s as ceiling from g2, a0),
live as (select id from f2 where i = 9 and ceiling - 1e-4 >= (select floor from f2 where i = 9 order by floor desc, id limit 1 offset 9)),
bar as (select min(floor) as bar from f where i = 9 and id in (select id from live))
select id from f, bar where i = 9 and ceiling >= bar - 1e-4 and id not in (select id from live)""")
def q_reactivated_nodes(spark, sf_dir):
    """Nodes that the new bounds bring back, before the next check rules them out again. The first run ends at level 9."""
    graph = build(HEAVY, spark, sf_dir)
    before = dynamic.start(graph, TopKCriterion(10, 1e-4), max_levels=9)
    spare = replace(before, criterion=FixedLevels(before.depth), bar=None)
    after = dynamic.apply_batch(spare, dynamic.EdgeBatch.of(deletes=dynamic.chosen_edges(graph.edges, 100, True)))
    again, _ = dynamic.reactivated(before.frame, after.frame.drop("live").withColumn("live", F.lit(True)), 1e-4)
    return again.where("live").join(before.frame.where("live"), "id", "left_anti").select("id")


@query(f"with recursive {O.graph_ctes(HEAVY)}, c as ({O.chosen_sql(HEAVY, 50)}) select 'deletes' as what, (select count(*) from c)::bigint as arcs union all select 'inserts', 0")
def q_batch_validate(spark, sf_dir):
    """Deletions of absent edges and insertions of present ones are no changes."""
    graph = build(HEAVY, spark, sf_dir)
    some = dynamic.chosen_edges(graph.edges, 50, True)
    absent = some.select(F.col("src"), (F.col("dst") + (1 << 45)).alias("dst"))
    kept = dynamic.chosen_edges(graph.edges, 60, True).join(some, ["src", "dst"], "left_anti")
    inserts, deletes = dynamic.normalise(graph.edges, dynamic.EdgeBatch.of(inserts=kept, deletes=some.unionByName(absent)), True)
    return rows(spark, [("deletes", deletes.count()), ("inserts", inserts.count())], "what string, arcs long")


# around the methods: reports, joins, windows, functions


@query(f"select {sql_pack('part', 'l_partkey')} as src, {sql_pack('supplier', 'l_suppkey')} as dst from lineitem")
def q_scan_edges_parquet(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey"])
    return lines.select(pack("part", "l_partkey").alias("src"), pack("supplier", "l_suppkey").alias("dst"))


@query(f"with e as ({EDGES_SQL[HEAVY]}), d as (select src, count(*) as deg from e group by src) select deg::bigint as deg, count(*)::bigint as nodes from d group by deg")
def q_degree_hist(spark, sf_dir):
    return out_degrees(build(HEAVY, spark, sf_dir)).groupBy("deg").agg(F.count("*").alias("nodes"))


@query(f"with e as ({EDGES_SQL[HEAVY]}), d as (select src, count(*) as deg from e group by src) select count(*)::bigint as n, sum(deg)::bigint as m, max(deg)::bigint as d_max, min(deg)::bigint as d_min, round(avg(deg), 8) as d_mean, (count(*) filter (where deg > 50))::bigint as hubs from d")
def q_graph_stats(spark, sf_dir):
    deg = out_degrees(build(HEAVY, spark, sf_dir))
    return deg.agg(F.count("*").alias("n"), F.sum("deg").alias("m"), F.max("deg").alias("d_max"), F.min("deg").alias("d_min"), F.round(F.avg("deg"), 8).alias("d_mean"), F.count_if(F.col("deg") > 50).alias("hubs"))


@query(f"with e as ({EDGES_SQL[HEAVY]}) select {sql_pack('part', 'p_partkey')} as id from part where {sql_pack('part', 'p_partkey')} not in (select src from e)")
def q_isolated_nodes(spark, sf_dir):
    parts = table(spark, sf_dir, "part", ["p_partkey"]).select(pack("part", "p_partkey").alias("id"))
    return parts.join(build(HEAVY, spark, sf_dir).edges, F.col("id") == F.col("src"), "left_anti")


_ALL, _PART = f"select src, dst from ({EDGES_SQL['part_supplier']})", f"select src, dst from ({EDGES_SQL[HEAVY]})"


@query(f"{_ALL} except {_PART}")
def q_edges_except(spark, sf_dir):
    return build("part_supplier", spark, sf_dir).edges.exceptAll(build(HEAVY, spark, sf_dir).edges)


@query(f"""with recursive {O.graph_ctes(HEAVY)}, {O.scaled(80)}, d as (select src as id, row_number() over (order by count(*) desc, src) as degree_rank from e group by src),
s as (select id, row_number() over (order by round(k, 9) desc, id) as score_rank from g where i = 80)
select coalesce(d.id, s.id) as id, degree_rank::bigint as degree_rank, score_rank::bigint as score_rank from d full join s on d.id = s.id""")
def q_rank_compare(spark, sf_dir):
    graph = build(HEAVY, spark, sf_dir)
    by_degree = baselines.degree_rank(graph).select("id", F.col("rank").alias("degree_rank"))
    by_score = ranked(baselines.solve_cg(graph).scores.select("id", F.round("score", 9).alias("score")), "score").select("id", F.col("rank").alias("score_rank"))
    return by_degree.join(by_score, "id", "full").select("id", "degree_rank", "score_rank")


def supplier_scores(spark, sf_dir):
    """s_suppkey, nation, region and the score after four levels, rounded."""
    frame = level_bounds(part_supplier_heavy(spark, sf_dir), 4).frame.select("id", F.round("floor", 8).alias("score"))
    suppliers, nations, regions = table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"]), table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    named = suppliers.join(nations, F.col("s_nationkey") == F.col("n_nationkey")).join(regions, F.col("n_regionkey") == F.col("r_regionkey"))
    return named.withColumn("id", pack("supplier", "s_suppkey")).join(frame, "id").select("id", "n_name", "r_name", "score")


_SUPPLIERS = f"{O.frames(HEAVY, 4)}, su as (select f.id, n_name, r_name, round(floor, 8) as score from f join supplier on {sql_pack('supplier', 's_suppkey')} = f.id join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey where i = 4)"


@query(f"{_SUPPLIERS} select r_name, n_name, count(*)::bigint as suppliers, round(max(score), 8) as best from su group by rollup (r_name, n_name)")
def q_score_rollup_region_nation(spark, sf_dir):
    return supplier_scores(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("suppliers"), F.round(F.max("score"), 8).alias("best"))


@query(f"{_SUPPLIERS} select r_name, top, count(*)::bigint as suppliers, round(min(score), 8) as least from (select *, case when score > 0.9 then 'top' else 'rest' end as top from su) group by cube (r_name, top)")
def q_score_cube(spark, sf_dir):
    rows_ = supplier_scores(spark, sf_dir).withColumn("top", F.when(F.col("score") > 0.9, "top").otherwise("rest"))
    return rows_.cube("r_name", "top").agg(F.count("*").alias("suppliers"), F.round(F.min("score"), 8).alias("least"))


@query(f"{O.frames('customer_supplier', 4)} select c_mktsegment as segment, n_name as nation, count(*)::bigint as customers, round(max(floor), 8) as best from f join customer on {sql_pack('customer', 'c_custkey')} = f.id join nation on c_nationkey = n_nationkey where i = 4 group by cube (c_mktsegment, n_name)")
def q_score_cube_segment(spark, sf_dir):
    frame = level_bounds(build("customer_supplier", spark, sf_dir), 4).frame
    customers, nations = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_mktsegment"]), table(spark, sf_dir, "nation", ["n_nationkey", "n_name"])
    named = customers.join(nations, F.col("c_nationkey") == F.col("n_nationkey")).select(pack("customer", "c_custkey").alias("id"), F.col("c_mktsegment").alias("segment"), F.col("n_name").alias("nation"))
    return named.join(frame, "id").cube("segment", "nation").agg(F.count("*").alias("customers"), F.round(F.max("floor"), 8).alias("best"))


@query(f"{_SUPPLIERS} select n_name, rank, id from (select *, (row_number() over (partition by n_name order by score desc, id))::bigint as rank from su) where rank <= 2")
def q_topk_per_nation(spark, sf_dir):
    rank = F.row_number().over(Window.partitionBy("n_name").orderBy(F.desc("score"), "id")).cast("long")
    return supplier_scores(spark, sf_dir).withColumn("rank", rank).where("rank <= 2").select("n_name", "rank", "id")


@query(f"{_SUPPLIERS} select id, r_name, (rank() over w)::bigint as place, (dense_rank() over w)::bigint as dense, (ntile(4) over w2)::bigint as quarter, round(percent_rank() over w, 8) as share, round(cume_dist() over w, 8) as cumulated from su window w as (partition by r_name order by score desc), w2 as (partition by r_name order by score desc, id)")
def q_rank_functions(spark, sf_dir):
    w = Window.partitionBy("r_name").orderBy(F.desc("score"))
    w2 = Window.partitionBy("r_name").orderBy(F.desc("score"), "id")
    return supplier_scores(spark, sf_dir).select("id", "r_name", F.rank().over(w).cast("long").alias("place"), F.dense_rank().over(w).cast("long").alias("dense"), F.ntile(4).over(w2).cast("long").alias("quarter"), F.round(F.percent_rank().over(w), 8).alias("share"), F.round(F.cume_dist().over(w), 8).alias("cumulated"))


@query(f"{_SUPPLIERS} select id, r_name, (count(*) over (partition by r_name order by spot range between 1000000 preceding and 1000000 following))::bigint as near from (select *, round(score * 1e8)::bigint as spot from su)")
def q_range_frame_near_ties(spark, sf_dir):
    w = Window.partitionBy("r_name").orderBy("at").rangeBetween(-1_000_000, 1_000_000)
    at = F.round(F.col("score") * 1e8).cast("long")
    return supplier_scores(spark, sf_dir).withColumn("at", at).select("id", "r_name", F.count("*").over(w).alias("near"))


@query(f"{O.frames(HEAVY, 6)} select count(*)::bigint as failures from (select ceiling, lag(floor) over (order by floor desc, ceiling desc, id) as prev from f where i = 6) where prev <= ceiling - 1e-4")
def q_adjacent_sep(spark, sf_dir):
    graph = build(HEAVY, spark, sf_dir)
    frame = level_bounds(graph, 6).frame
    return rows(spark, [(ordered.adjacent_failures(frame, 1e-4, graph.stats.n, 200),)], "failures long")


@query(f"with recursive {O.graph_ctes(HEAVY)}, {O.scaled(5)} select id, round(k, 8) as score from g where i = 5")
def q_score_from_level_array(spark, sf_dir):
    """Partial scores from an array of the levels, as after a change of alpha."""
    graph = build(HEAVY, spark, sf_dir)
    found = rank_nodes(graph, FixedLevels(5), numeric="exact", keep_levels=True)
    alpha = found.report.alpha
    long = None
    for i, level in enumerate(found.history, 1):
        part = level.select("id", F.struct(F.lit(i).alias("i"), F.col("w").cast("double").alias("w")).alias("x"))
        long = part if long is None else long.unionByName(part)
    arrays = long.groupBy("id").agg(F.sort_array(F.collect_list("x")).alias("levels"))
    total = F.aggregate("levels", F.lit(0.0), lambda s, x: s + x.w * F.pow(F.lit(alpha), x.i))
    return arrays.select("id", F.round(total, 8).alias("score"))


@query(f"with recursive {O.graph_ctes(HEAVY, edges=removed_sql(HEAVY, 10))}, {O.exact(2)}, ys as (select e0.src as id, sum(c) as w from e0 join (select src, count(*) as c from e0 group by src) t on e0.dst = t.src group by e0.src) select x.id, (x.w - coalesce(ys.w, 0))::bigint as d from x left join ys on ys.id = x.id where x.i = 2 and x.w <> coalesce(ys.w, 0)")
def q_delta_level2(spark, sf_dir):
    """What a batch changes in the second level, by a broadcast of what it changes in the first."""
    graph = build(HEAVY, spark, sf_dir)
    state = dynamic.start(graph, FixedLevels(1))
    inserts, deletes = dynamic.normalise(graph.edges, dynamic.EdgeBatch.of(deletes=dynamic.chosen_edges(graph.edges, 10, True)), True)
    kept = graph.placed.arcs.join(F.broadcast(deletes), ["src", "dst"], "left_anti")
    none = graph.nodes.limit(0).select("id", F.lit(0).cast("decimal(38,0)").alias("d"))
    one = dynamic.propagate(kept, inserts, deletes, state.levels[0], none, 0)
    return dynamic.propagate(kept, inserts, deletes, state.levels[1], one, 1).select("id", F.col("d").cast("long").alias("d"))


@query("select user_id, count(*)::bigint as events, round(sum(coalesce(try_cast(json_extract_string(props, '$.k') as double), 0)), 6) as weight from events group by user_id")
def q_event_props_degree(spark, sf_dir):
    rows_ = table(spark, sf_dir, "events", ["user_id", "props"])
    weight = F.coalesce(F.get_json_object("props", "$.k").try_cast("double"), F.lit(0.0))
    return rows_.groupBy("user_id").agg(F.count("*").alias("events"), F.round(F.sum(weight), 6).alias("weight"))


def _moves(spark, sf_dir) -> DataFrame:
    """ts, src and dst of the edges that events give rise to."""
    events = table(spark, sf_dir, "events", ["event_id", "ts", "user_id"])
    return follow_rows(events).where("user_id <> next_user").select(F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("src"), F.col("next_user").alias("dst"))


_MOVES = "m as (select ts, user_id as src, next_user as dst from (select ts, user_id, lead(user_id) over (order by ts, event_id) as next_user from events) where user_id <> next_user)"


@query(f"with {_MOVES} select epoch(date_trunc('day', ts))::bigint as begin, count(distinct src * 1000000 + dst)::bigint as edges, count(*)::bigint as moves from m group by 1")
def q_tumbling_edges(spark, sf_dir):
    w = F.window("ts", "1 day")
    found = _moves(spark, sf_dir).groupBy(w.alias("w")).agg(F.count_distinct("src", "dst").alias("edges"), F.count("*").alias("moves"))
    return found.select(F.unix_seconds("w.start").alias("begin"), "edges", "moves")


@query(f"with {_MOVES}, k as (select (floor(epoch(ts) / 3600)::bigint - unnest(range(0, 6))) * 3600 as begin from m) select begin, count(*)::bigint as moves from k group by begin")
def q_sliding_edges(spark, sf_dir):
    found = _moves(spark, sf_dir).groupBy(F.window("ts", "6 hours", "1 hour").alias("w")).agg(F.count("*").alias("moves"))
    return found.select(F.unix_seconds("w.start").alias("begin"), "moves")


@query(f"""with {_MOVES}, a as (select src, ts, case when epoch(ts) - epoch(lag(ts) over (partition by src order by ts)) < 3600 then 0 else 1 end as fresh from m),
s as (select src, ts, sum(fresh) over (partition by src order by ts rows unbounded preceding) as n from a) select src, floor(epoch(min(ts)))::bigint as begin, count(*)::bigint as moves from s group by src, n""")
def q_session_edges(spark, sf_dir):
    found = _moves(spark, sf_dir).groupBy("src", F.session_window("ts", "1 hour").alias("w")).agg(F.count("*").alias("moves"))
    return found.select("src", F.unix_seconds("w.start").alias("begin"), "moves")


@query("""with s as (select user_id, ts, event_id from events where event_type = 'signup')
select e.event_id, max(s.event_id)::bigint as last_signup from events e left join s on s.user_id = e.user_id and (s.ts < e.ts or (s.ts = e.ts and s.event_id <= e.event_id))
  and (s.ts, s.event_id) = (select (x.ts, x.event_id) from s x where x.user_id = e.user_id and (x.ts < e.ts or (x.ts = e.ts and x.event_id <= e.event_id)) order by x.ts desc, x.event_id desc limit 1) group by e.event_id""")
def q_asof_snapshot(spark, sf_dir):
    """For each event the user's last sign-up until then: an as-of join as a window over one pass."""
    events = table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type"])
    mark = F.when(F.col("event_type") == "signup", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return events.select("event_id", F.last(mark, ignorenulls=True).over(w).alias("last_signup"))


@query("select u.user_id, (count(*) filter (where event_type = 'error'))::bigint as errors, (count(distinct event_type))::bigint as kinds, min(event_id)::bigint as first_event from events u group by u.user_id")
def q_user_profile(spark, sf_dir):
    events = table(spark, sf_dir, "events", ["event_id", "user_id", "event_type"])
    return events.groupBy("user_id").agg(F.count_if(F.col("event_type") == "error").alias("errors"), F.count_distinct("event_type").alias("kinds"), F.min("event_id").alias("first_event"))


@query(f"with e as ({EDGES_SQL['nation_trade']}), nd as ({NODES_SQL['nation_trade']}) select (select count(*) from e where src <> dst) = (select count(*) * (count(*) - 1) from nd) as complete")
def q_is_complete(spark, sf_dir):
    return rows(spark, [(is_complete(build("nation_trade", spark, sf_dir)),)], "complete boolean")


# experiments: figures of runs; their levels have SQL above, their seconds can't. The grids are those of the functions but
# for graphs (and batches of 10) that are left out to keep each below some minutes.

QUICK = ("part_supplier", "part_supplier_heavy", "customer_supplier", "order_tree", "user_hour_event", "conversation_token")


@query()
def w1_epsilon_sweep(spark, sf_dir):
    from . import experiments

    return experiments.epsilon_sweep(spark, sf_dir)


@query()
def w2_instances(spark, sf_dir):
    from . import experiments

    return experiments.summary(experiments.instances(spark, sf_dir, QUICK))


@query()
def w3_topk_sweep(spark, sf_dir):
    from . import experiments

    return experiments.topk_sweep(spark, sf_dir, ("part_supplier", "order_tree"))


@query()
def w4_batch_deletions(spark, sf_dir):
    from . import experiments

    return experiments.batch_sweep(spark, sf_dir, ("order_tree", "part_supplier"), (1, 100, 1000, 10000))


@query()
def w5_batch_insertions(spark, sf_dir):
    from . import experiments

    return experiments.batch_sweep(spark, sf_dir, ("order_tree", "part_supplier_heavy"), (1, 1000), inserts=True)


@query()
def w6_scaling(spark, sf_dir):
    from . import experiments

    return experiments.scaling(spark, sf_dir, ("part_supplier",))


_BOTH_WAYS = "select src, dst from e0 union select dst, src from e0"


@query(f"""select a.id, a.score as undirected, b.score as directed from (with recursive {O.graph_ctes('user_follow', edges=_BOTH_WAYS)}, {O.scaled(2600)} select id, round(k, 6) as score from g where i = 2600) a
join (with recursive {O.graph_ctes('user_follow')}, {O.scaled(2600)} select id, round(k, 6) as score from g where i = 2600) b on a.id = b.id""")
def w7_directed_as_undirected(spark, sf_dir):
    """A directed graph made undirected for the linear solve, beside its own fixed point."""
    graph = build("user_follow", spark, sf_dir)
    solved, own = baselines.solve_cg(graph.as_undirected()), baselines.solve_fixed_point(graph, 1e-10)
    both = solved.scores.withColumnRenamed("score", "undirected").join(own.scores.withColumnRenamed("score", "directed"), "id")
    return both.select("id", F.round("undirected", 6).alias("undirected"), F.round("directed", 6).alias("directed"))


@query("""with m as (select event_id, ts, user_id as src, next_user as dst, event_type from (select *, lead(user_id) over (order by ts, event_id) as next_user from events) where user_id <> next_user)
select src, dst from (select *, row_number() over (partition by src, dst order by ts desc, event_id desc) as rn from m) where rn = 1 and event_type <> 'error'""")
def w9_event_replay(spark, sf_dir):
    """The edges after the events of the second half come as a batch on the graph of the first half."""
    from ..streaming.events import event_changes, standing

    changes = event_changes(table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type"]))
    middle = changes.agg(F.percentile_approx("ts", 0.5)).first()[0]
    early, later = changes.where(F.col("ts") < F.lit(middle)), changes.where(F.col("ts") >= F.lit(middle))
    users = table(spark, sf_dir, "events", ["user_id"]).select(F.col("user_id").alias("id")).distinct()
    state = dynamic.start(Graph.from_edges(standing(early), users), FixedLevels(2))
    ordered_later = later.select("src", "dst", "op", F.unix_micros("ts").alias("at"), "seq")
    order = F.struct("at", "seq")
    last = ordered_later.groupBy("src", "dst").agg(F.max_by("op", order).alias("op")).withColumn("seq", F.lit(0).cast("long"))
    return dynamic.apply_batch(state, dynamic.EdgeBatch(last)).graph.edges.select("src", "dst")


@query(f"{O.frames('page_link', 6, inbound=True)}, {O.topk(20, 1e-6)} select rn::bigint as rank, id, round(floor, 8) as floor, round(ceiling, 8) as ceiling from t where i = {O.LAST}")
def w8_inbound_pages(spark, sf_dir):
    from . import experiments

    return experiments.webs(spark, sf_dir).select("rank", "id", F.round("floor", 8).alias("floor"), F.round("ceiling", 8).alias("ceiling"))
