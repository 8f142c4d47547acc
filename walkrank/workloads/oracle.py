"""SQL of the same results: levels by a recursive query, bounds and criteria evaluated at each level."""

from __future__ import annotations

from .graphs import DIRECTED, EDGES_SQL, NODES_SQL


def chosen_sql(graph: str, count: int) -> str:
    """The arcs of chosen edges, both ways if the graph is undirected."""
    once = "where src < dst" if graph not in DIRECTED else ""
    pick = f"select src, dst from e0 {once} order by (src * 1000003 + dst * 7919) % 2147483647, src, dst limit {count}"
    return f"select src, dst from ({pick})" if graph in DIRECTED else f"with c as ({pick}) select src, dst from c union select dst, src from c"


def graph_ctes(graph: str, inbound: bool = False, edges: str | None = None, nodes: str | None = None, alpha: str | None = None) -> str:
    """e (src, dst), nd (id) and p (d_max, alpha, gamma). edges: another query over e0; nodes: of e0 if the graph has changed."""
    own = EDGES_SQL[graph]
    parts = [f"e0 as materialized ({own})"]
    arcs = edges or "select src, dst from e0"
    if inbound:
        arcs = f"select dst as src, src as dst from ({arcs})"
    parts.append(f"e as materialized ({arcs})")
    node_sql = NODES_SQL[graph].replace(" from e union", " from e0 union").replace(" from e ", " from e0 ")
    if node_sql.endswith(" from e"):
        node_sql = node_sql[: -len(" from e")] + " from e0"
    parts.append(f"nd as materialized ({nodes or node_sql})")
    parts.append("dm as (select max(c) as d_max from (select count(*) as c from e group by src))")
    factor = alpha or "1.0::double / (1 + d_max)"
    parts.append(f"p as materialized (select d_max, alpha, d_max / (1 - alpha * d_max) as gamma from (select d_max, {factor} as alpha from dm))")
    return ",\n".join(parts)


def scaled(levels: int) -> str:
    """w (i, id, s), sparse; g (i, id, s, k) for all nodes."""
    return f"""w as (select 0 as i, id, 1.0::double as s from nd union all
  select w.i + 1, e.src, sum(w.s) * max(p.alpha) from w join e on e.dst = w.id, p where w.i < {levels} group by w.i, e.src),
g as materialized (select l.i, nd.id, coalesce(w.s, 0.0) as s, sum(coalesce(w.s, 0.0)) over (partition by nd.id order by l.i) as k
  from nd cross join (select unnest(range(1, {levels + 1}))::int as i) l left join w on w.i = l.i and w.id = nd.id)"""


def bounds(undirected: bool) -> str:
    floor = "k + alpha * s" if undirected else "k"
    return f"f as materialized (select i, id, {floor} as floor, k + alpha * gamma * s as ceiling from g, p)"


def frames(graph: str, levels: int, inbound: bool = False, **kw) -> str:
    return f"with recursive {graph_ctes(graph, inbound, **kw)},\n{scaled(levels)},\n{bounds(graph not in DIRECTED)}"


def exact(levels: int) -> str:
    """x (i, id, w): whole walk counts of all nodes."""
    return f"""xs as (select 0 as i, id, 1::hugeint as w from nd union all
  select xs.i + 1, e.src, sum(xs.w)::hugeint from xs join e on e.dst = xs.id where xs.i < {levels} group by xs.i, e.src),
x as materialized (select l.i, nd.id, coalesce(xs.w, 0)::hugeint as w from nd cross join (select unnest(range(0, {levels + 1}))::int as i) l left join xs on xs.i = l.i and xs.id = nd.id)"""


def topk(k: int, eps: float) -> str:
    """v (i, live, done): the top-k criterion at each level; t: the top rows."""
    return f"""fr as (select *, row_number() over (partition by i order by floor desc, id) as rn, count(*) over (partition by i) as n from f),
t as (select * from fr where rn <= {k}),
bar as (select i, min(floor) as bar, max(n) as n from t group by i),
apart as (select i, count(*) filter (where prev <= ceiling - {eps!r}) as bad from (select i, ceiling, lag(floor) over (partition by i order by floor desc, id) as prev from t) group by i),
v as (select bar.i, count(*) as live, count(*) <= least({k}, max(bar.n)) and max(apart.bad) = 0 as done from fr join bar on fr.i = bar.i join apart on apart.i = bar.i where fr.rn <= {k} or fr.ceiling - {eps!r} >= bar.bar group by bar.i)"""


def ranking(eps: float) -> str:
    """v (i, done): the ranking criterion at each level."""
    return f"""v as (select i, count(*) filter (where prev <= ceiling - {eps!r}) = 0 as done
  from (select i, ceiling, lag(floor) over (partition by i order by floor desc, ceiling desc, id) as prev from f) group by i)"""


LAST = "(select min(i) from v where done)"
