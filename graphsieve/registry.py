"""Every registered query and, where SQL can tell it, its oracle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from graphsieve import relational
from graphsieve.functions.python_functions import Relaxations, bucketed_labels, cosine, jaccard, triangles_of
from graphsieve.functions.storage import materialize, new_path
from graphsieve.operators import baselines, explore, layout, measures
from graphsieve.operators.components import connected_components
from graphsieve.operators.reduce import init_candidates, neighbourhood_fixpoint, relaxed_superset
from graphsieve.operators.sieve import LOCAL_EDGES, centrality, count_matches, enumerate_matches, estimate_matches, has_match, rules_of, sieve
from graphsieve.operators.walks import walk_sources
from graphsieve.plans.rules import Rule, full_cover
from graphsieve.plans.template import Template
from graphsieve.sources import sinks
from graphsieve.sources.graphs import GRAPHS, HREF, degree_label, domain_label, fill, oracle_matches, oracle_prefix, sql_domain_label
from graphsieve.streaming import events as streams
from graphsieve.workloads import CLIQUE4, CLIQUE6, WORKLOADS, graph, once, solution, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return add


def _mask_sql(t: Template, mapped: str = "m") -> str:
    return " union all ".join(f"select r{q} as vid, {q} as role from {mapped}" for q in range(t.n))


def _edge_sql(t: Template, mapped: str = "m") -> str:
    return " union ".join(f"select r{a} as src, r{b} as dst from {mapped} union select r{b}, r{a} from {mapped}" for a, b in t.edges)


# ---- answers of all workloads ---------------------------------------------------------------------------------------------------
for _w, (_g, _t) in WORKLOADS.items():
    _m = oracle_matches(_g, _t)
    query(f"sol_vertices_{_w}", f"{_m} select distinct vid, role from ({_mask_sql(_t)}) x")(lambda s, d, w=_w: solution(s, d, w).role_map())
    query(f"sol_edges_{_w}", f"{_m} {_edge_sql(_t)}")(lambda s, d, w=_w: solution(s, d, w).edges)
    query(f"count_{_w}", f"{_m} select count(*) as embeddings, cast(count(*) / {len(_t.automorphisms)} as bigint) as subgraphs from m")(
        lambda s, d, w=_w: count_matches(solution(s, d, w)).select(F.col("n").alias("embeddings"), F.expr(f"n div {len(WORKLOADS[w][1].automorphisms)}").alias("subgraphs"))
    )

T2, T6 = WORKLOADS["w2"][1], WORKLOADS["w6"][1]
_M2, _M6 = oracle_matches(*WORKLOADS["w2"]), oracle_matches(*WORKLOADS["w6"])
query("matches_w2", f"{_M2} select r0, r1, r2 from m")(lambda s, d: enumerate_matches(solution(s, d, "w2")))
query("matches_w6", f"{_M6} select r0, r1, r2, r3, r4 from m")(lambda s, d: enumerate_matches(solution(s, d, "w6")))
query("matches_shipped", f"{oracle_matches(*WORKLOADS['shipped'])} select r0, r1, r2 from m")(lambda s, d: enumerate_matches(solution(s, d, "shipped")))
query("subgraphs_road_c3", f"{oracle_matches(*WORKLOADS['road_c3'])} select count(*) as n from m where r0 < r1 and r1 < r2")(lambda s, d: count_matches(solution(s, d, "road_c3"), "subgraphs"))
query("subgraphs_road_c4", f"{oracle_matches(*WORKLOADS['road_c4'])} select count(*) as n from m where r0 < r1 and r1 < r2 and r2 < r3")(lambda s, d: count_matches(solution(s, d, "road_c4"), "subgraphs"))
query("count_buckets_w5", f"{oracle_matches(*WORKLOADS['w5'])} select count(*) as n from m")(lambda s, d: count_matches(solution(s, d, "w5"), buckets=3))
query("induced_w2_path", f"{oracle_matches('trade', T2.without((0, 2)))} select r0, r1, r2 from m where not exists (select 1 from ge where src = r0 and dst = r2)")(
    lambda s, d: enumerate_matches(sieve(graph(s, d, "trade"), T2.without((0, 2))), induced_in=graph(s, d, "trade").edges)
)
query("centrality_vertices_w2", f"{_M2} select vid, count(*) as n from ({_mask_sql(T2)}) x group by vid order by n desc, vid limit 50")(lambda s, d: centrality(solution(s, d, "w2"), "vertex", 50))
query("centrality_roles_w2", f"{_M2} select vid, role, count(*) as n from ({_mask_sql(T2)}) x group by vid, role")(lambda s, d: centrality(solution(s, d, "w2"), "role"))
query("centrality_edges_w2", f"{_M2} select least(u, v) as src, greatest(u, v) as dst, count(*) as n from (select r0 as u, r1 as v from m union all select r1, r2 from m union all select r0, r2 from m) x group by 1, 2")(lambda s, d: centrality(solution(s, d, "w2"), "edge"))
query("solution_size_w2", f"{_M2} select (select count(distinct vid) from ({_mask_sql(T2)}) x) as v_star, (select count(*) from ({_edge_sql(T2)}) y) as e_star")(lambda s, d: measures.solution_size(solution(s, d, "w2")))
for _w in ("w2", "exists_none", "w6", "rmat_even_seven"):
    _g, _t = WORKLOADS[_w]
    query(f"exists_{_w}".replace("exists_exists_", "has_"), f"{oracle_matches(_g, _t)} select count(*) > 0 as found from m")(lambda s, d, g=_g, t=_t: s.createDataFrame([(has_match(graph(s, d, g), t),)], "found boolean"))
query("exists_distributed_w6", f"{_M6} select count(*) > 0 as found from m")(lambda s, d: s.createDataFrame([(has_match(graph(s, d, "trade"), T6, local_below=0),)], "found boolean"))

# ---- the same answers by the distributed engine alone, and by every option --------------------------------------------------------
_FAR = {"local_below": 0, "least_gain": 0}
for _w in ("w2", "w3", "w6", "topo_b", "shipped"):
    _g, _t = WORKLOADS[_w]
    query(f"distributed_{_w}", f"{oracle_matches(_g, _t)} {_edge_sql(_t)}")(lambda s, d, g=_g, t=_t: sieve(graph(s, d, g, t), t, **_FAR).edges)
for _name, _opts in {
    "abl_set_rule": {"rule": "set"}, "abl_count_rule": {"rule": "count"}, "abl_vertices_only": {"eliminate": "vertices"}, "abl_no_fold": {"how": "none"}, "abl_issuer": {"how": "issuer"}, "abl_every_start": {"starts": "every"},
    "abl_rarest_start": {"starts": "rarest"}, "abl_given_order": {"policy": "given"}, "abl_rarest_first": {"policy": "rarest_first"}, "abl_extra_covers": {"extra": 4}, "abl_switch": {"switch_below": 10_000_000},
    "abl_least_gain": {"least_gain": 0.5}, "abl_switch_distributed": {"switch_below": 10_000_000, **_FAR}, "abl_smaller_deployment": {"local_below": 5_000},
}.items():
    query(_name, f"{_M6} {_edge_sql(T6)}")(lambda s, d, o=_opts: sieve(graph(s, d, "trade", T6), T6, **({"least_gain": 0} | o)).edges)
for _name, _opts in {"abl_buckets": {"buckets": 2}, "abl_hubs": {"hub_degree": 50}, "abl_no_fold_distributed": {"how": "none", "starts": "rarest"}, "abl_issuer_distributed": {"how": "issuer"}, "abl_vertices_only_distributed": {"eliminate": "vertices"}}.items():
    query(_name, f"{_M2} {_edge_sql(T2)}")(lambda s, d, o=_opts: sieve(graph(s, d, "trade", T2), T2, **o, **_FAR).edges)
for _w, _how in (("rank_q8", "every"), ("w9", "every"), ("topo_c", "rarest")):
    _g, _t = WORKLOADS[_w]
    query(f"abl_starts_{_how}_{_w}", f"{oracle_matches(_g, _t)} {_edge_sql(_t)}")(lambda s, d, g=_g, t=_t, h=_how: sieve(graph(s, d, g, t), t, starts=h, least_gain=0).edges)


@query("abl_rebalance", f"{_M2} {_edge_sql(T2)}")
def _rebalanced(s, d):
    g = graph(s, d, "trade")
    return sieve(g, T2, state=layout.consolidate(layout.rebalance(neighbourhood_fixpoint(init_candidates(g, T2), T2)))).edges


@query("abl_rebalance_w12", f"{oracle_matches(*WORKLOADS['w12'])} {_edge_sql(WORKLOADS['w12'][1])}")
def _rebalanced_threads(s, d):
    """Threads hang on hubs: reduced, dealt anew, and reduced on."""
    g, t = graph(s, d, "conv"), WORKLOADS["w12"][1]
    return sieve(g, t, state=layout.rebalance(neighbourhood_fixpoint(init_candidates(g, t), t), 8), **_FAR).edges


@query("resume_w2", f"{_M2} {_edge_sql(T2)}")
def _resumed(s, d):
    path = new_path(s, "snapshot")
    layout.save(neighbourhood_fixpoint(init_candidates(graph(s, d, "trade"), T2), T2), path)
    return sieve(None, T2, state=layout.load(s, path)).edges


def _hops_sql(t: Template, start: int) -> str:
    """Distinct tokens of a whole walk by the plan's live positions cannot be told in general; of the triangle they can."""
    return f"""select 'none' as fold, 1 as hop, (select count(*) from a) as tokens union all select 'none', 2, (select count(*) from b)
    union all select 'live', 1, (select count(*) from a) union all select 'live', 2, (select count(distinct r{start}) from b)"""


@query("abl_fold_tokens", f"{_M2}, a as (select src, dst from (select e.src, e.dst from ge e join gv x on x.vid = e.src and x.label = 'supplier' join gv y on y.vid = e.dst and y.label = 'order:F')), b as (select r0, r1, r2 from m) {_hops_sql(T2, 2)}")
def _fold_tokens(s, d):
    """Tokens of a walk over the whole triangle from its suppliers, by hop, with and without folding."""
    state = init_candidates(graph(s, d, "trade"), T2)
    rows = []
    for how in ("none", "live"):
        walk_sources(state, Rule("cover", 2, full_cover(T2).edges), how, {"order:F": 1, "part:PROMO": 2}, seen=(seen := []))
        rows += [(how, r["hop"], r["tokens"]) for r in seen]
    return s.createDataFrame(rows, "fold string, hop int, tokens long")


@query("abl_fold_work")
def _fold_work(s, d):
    """Tokens and completed walks with every way of folding, on workloads with many walks."""
    rows = []
    for w in ("w6", "rank_q8", "topo_c"):
        name, t = WORKLOADS[w]
        start = neighbourhood_fixpoint(init_candidates(graph(s, d, name, t), t), t, enough=LOCAL_EDGES)  # the same for every way
        for how in ("none", "live", "issuer"):
            x = sieve(None, t, state=start, how=how, starts="rarest", least_gain=0, count_tokens=True)
            rows.append((w, how, sum(r.get("tokens", 0) for r in x.trace), sum(r.get("walks", 0) for r in x.trace), x.state.rows))
    return s.createDataFrame(rows, "workload string, fold string, tokens long, walks long, e_star long")


@query("precision_stages_w2")
def _precision(s, d):
    return _precisions(s, d, "w2", (0, 1, None))


@query("precision_stages_w6")
def _precision6(s, d):
    return _precisions(s, d, "w6", (0, 1, 2, 3, None))


def _precisions(s, d, w, stops):
    """Precision and recall when stopping after 0, 1, ... rules, and confirmed; recall is always 1."""
    name, t = WORKLOADS[w]
    start, checked, rows = neighbourhood_fixpoint(init_candidates(graph(s, d, name, t), t), t, enough=LOCAL_EDGES), [], []  # every search starts from it
    truth = sieve(None, t, state=start)
    state = start
    for k in stops:
        if k is None:
            x = truth
        else:  # goes on from the stop before
            x = sieve(None, t, max_rules=k - len(checked), state=state, checked=tuple(checked))
            checked, state = [*checked, *rules_of(x.trace)], x.state
            checked += [("none", "")] * (k - len(checked))  # there were no more rules
        e, v = measures.precision_recall(x.edges, truth.edges, ["src", "dst"]), measures.precision_recall(x.state.masks, truth.state.masks, ["vid"])
        rows.append(("confirmed" if k is None else f"{k} rules", v["precision"], v["recall"], e["precision"], e["recall"]))
    return s.createDataFrame(rows, "stage string, v_precision double, v_recall double, e_precision double, e_recall double")


@query("estimate_w2")
def _estimate(s, d):
    e = estimate_matches(solution(s, d, "w2"))
    return s.createDataFrame([(e["estimate"], e["error"])], "estimate double, error double")


_TRACE = "seq int, stage string, rule string, rounds int, v long, e long, messages long, tokens long, seconds double"
query("trace_w6")(lambda s, d: s.createDataFrame(measures.phase_seconds(solution(s, d, "w6")), _TRACE))
query("trace_distributed_w2")(lambda s, d: s.createDataFrame(measures.phase_seconds(sieve(graph(s, d, "trade"), T2, **_FAR)), _TRACE))


@query("reduction_w6")
def _reduction(s, d):
    r = measures.reduction(graph(s, d, "trade"), solution(s, d, "w6"))
    return s.createDataFrame([("vertices", r["vertices"]), ("edges", r["edges"]), *((f"{k} {x}", y) for k, (x, y) in enumerate(r["stages"]))], "what string, times double")


@query("state_bytes_w6")
def _bytes(s, d):
    own = measures.state_bytes(solution(s, d, "w6"))
    return s.createDataFrame([*own.items(), ("orders", measures.dataset_bytes(s, f"{d}/orders.parquet"))], "what string, bytes long")


query("components_w6", f"with recursive {_M6[5:]}, ke as materialized ({_edge_sql(T6)}), r(vid, top) as (select src, src from ke union select ke.dst, r.top from r join ke on ke.src = r.vid where ke.dst <> r.top), c as (select vid, min(top) as component from r group by vid) select c.component, count(*) as vertices, (select count(*) from m join c o on o.vid = m.r0 where o.component = c.component) as matches from c group by c.component")(
    lambda s, d: measures.solution_components(solution(s, d, "w6"))
)
query("imbalance_w6")(lambda s, d: measures.imbalance(solution(s, d, "w6").edges))
query("imbalance_report")(lambda s, d: measures.imbalance_summary(solution(s, d, "w12").edges, centrality(solution(s, d, "w12"))))


@query("scaling_report")
def _scaling(s, d):
    """Seconds, speedup and CPU hours of one distributed search at 1, 4 and 8 shuffle partitions."""
    rows = measures.scaling_report(lambda n: sieve(graph(s, d, "session"), WORKLOADS["w3"][1], switch_below=1 << 62, **_FAR), [1, 4, 8], s)
    return s.createDataFrame([(r["partitions"], r["seconds"], r["speedup"], r["cpu_hours"], r["cpu_hours_relative"]) for r in rows], "partitions int, seconds double, speedup double, cpu_hours double, cpu_hours_relative double")


@query("load_cost")
def _load(s, d):
    """Seconds to make a graph from the tables: apart from all search times."""
    from graphsieve.sources.graphs import build, free

    rows = []
    for name in ("trade", "session"):
        times = measures.timed(lambda name=name: free(build(s, d, name)), 1)
        rows.append((name, times["mean"]))
    return s.createDataFrame(rows, "graph string, seconds double")


@query("time_to_solution")
def _times(s, d):
    """Mean, least and most seconds of reduction and counting, of three runs (``measures.timed`` runs ten by default); loading is not in."""
    rows = []
    for w in ("w2", "w6", "rank_q8"):
        g, t = graph(s, d, WORKLOADS[w][0]), WORKLOADS[w][1]
        x = measures.timed(lambda g=g, t=t: count_matches(sieve(g, t)).first(), 3)
        rows.append((w, x["mean"], x["least"], x["most"]))
    return s.createDataFrame(rows, "workload string, mean double, least double, most double")


# ---- baselines: the same answers another way --------------------------------------------------------------------------------------
for _name, _hint in (("baseline_triple_w2", None), ("baseline_shuffle_hash_w2", "shuffle_hash"), ("baseline_merge_w2", "merge")):
    query(_name, f"{_M2} select r0, r1, r2 from m")(lambda s, d, h=_hint: baselines.triple_join(graph(s, d, "trade"), T2, h))
query("baseline_triple_w6", f"{_M6} select count(*) as n from m")(lambda s, d: baselines.triple_join(graph(s, d, "trade"), T6).agg(F.count("*").alias("n")))
query("baseline_direct_w6", f"{_M6} select count(*) as n from m")(lambda s, d: baselines.direct_enumerate(graph(s, d, "trade"), T6).agg(F.count("*").alias("n")))
query("baseline_replicated_w2", f"{_M2} select r0, r1, r2 from m")(lambda s, d: baselines.replicated_enumerate(graph(s, d, "trade"), T2))
_P = "with " + oracle_prefix("coorder") + ", up as materialized (select src, dst from ge where src < dst)"
_C3 = "c3 as materialized (select a.src as x, a.dst as y, b.dst as z from up a join up b on a.dst = b.src join up c on c.src = a.src and c.dst = b.dst)"
_C4 = "c4 as materialized (select a.x, b.z as w from c3 a join c3 b on b.x = a.y and b.y = a.z)"
query("clique3", f"{_P}, {_C3} select count(*) as n from c3")(lambda s, d: baselines.clique_grow(graph(s, d, "coorder").edges, 3).agg(F.count("*").alias("n")))
query("clique4", f"{_P}, {_C3}, {_C4} select count(*) as n from c4 join up e on e.src = x and e.dst = w")(lambda s, d: baselines.clique_grow(graph(s, d, "coorder").edges, 4).agg(F.count("*").alias("n")))
query("clique3_sieve", f"{_P}, {_C3} select count(*) as n from c3")(lambda s, d: (lambda t: count_matches(sieve(graph(s, d, "coorder", t), t), "subgraphs"))(Template.unlabelled([(0, 1), (0, 2), (1, 2)])))
query("clique4_sieve", f"{_P}, {_C3}, {_C4} select count(*) as n from c4 join up e on e.src = x and e.dst = w")(
    lambda s, d: (lambda t: count_matches(sieve(graph(s, d, "coorder", t), t, switch_below=1 << 62), "subgraphs"))(Template.unlabelled([(a, b) for b in range(4) for a in range(b)]))
)

# ---- revisions and exploration -----------------------------------------------------------------------------------------------------
_X2 = Template.build(CLIQUE4[1].labels, [(0, 1), (0, 2), (1, 2), (0, 3)])


def _explored(s, d, which, **options):
    return once(s, d, ("explore", which, *options), lambda: explore.explore(graph(s, d, which[0]), which[1], **options))


_LEVELS = "level int, variants long, solved long, matched long, walked long, reused long, v long"


def _levels(s, r):
    keys = ("level", "variants", "solved", "matched", "walked", "reused", "v")
    return s.createDataFrame([(*(int(x[k]) for k in keys), float(x["seconds_each"])) for x in r.levels], _LEVELS + ", seconds_each double")


query("explore_clique4", f"{oracle_matches('trade', _X2)} {_edge_sql(_X2)}")(lambda s, d: _explored(s, d, CLIQUE4).union_edges())
query("explore_clique4_distributed", f"{oracle_matches('trade', _X2)} {_edge_sql(_X2)}")(lambda s, d: _explored(s, d, CLIQUE4, local_below=0, max_level=2).union_edges())
query("explore_clique6")(lambda s, d: (lambda r: r.union_edges() if r.found is not None else s.createDataFrame([], "src long, dst long"))(_explored(s, d, CLIQUE6)))
query("explore_clique6_levels")(lambda s, d: _levels(s, _explored(s, d, CLIQUE6)))
query("relaxed_superset_clique4", f"{oracle_matches('trade', _X2)} select count(*) as missed from ({_edge_sql(_X2)}) x where false")(
    lambda s, d: _explored(s, d, CLIQUE4).union_edges().join(relaxed_superset(graph(s, d, "trade"), CLIQUE4[1]).edges, ["src", "dst"], "left_anti").agg(F.count("*").alias("missed"))
)

_PATH = T6.without((0, 2), (2, 4))
_STEPS = [("add", 0, 2), ("add", 2, 4), ("remove", 0, 1)]
for _k, _t in enumerate([_PATH, _PATH.with_edge(0, 2), T6, T6.without((0, 1))]):
    for _mode in ("superset_memo", "superset"):

        def _revised(s, d, k=_k, mode=_mode):
            return once(s, d, ("revisions", mode), lambda: explore.Revisions(graph(s, d, "trade", T6), _PATH, _STEPS, T6, mode))[k].role_map()

        query(f"incr_{_k}" if _mode == "superset_memo" else f"incr_{_mode}_{_k}", f"{oracle_matches('trade', _t)} select distinct vid, role from ({_mask_sql(_t)}) x")(_revised)


@query("session_stats", f"{_M2} select count(distinct vid) as vertices, (select count(*) from ({_edge_sql(T2)}) y) as edges, count(*) as candidates from (select distinct vid, role from ({_mask_sql(T2)}) x) z")
def _stats(s, d):
    """Statistics while a template is revised: here after the triangle's last edge is added."""
    session = explore.IncrementalSession(graph(s, d, "trade"), T2.without((0, 2)), T2)
    session.add_edge(0, 2)
    x = session.stats()
    return s.createDataFrame([(x["vertices"], x["edges"], x["candidates"])], "vertices long, edges long, candidates long")


# ---- graphs and their helpers ------------------------------------------------------------------------------------------------------
for _g in GRAPHS:
    _more = ", elabel" if _g == "shipped" else ""
    query(f"graph_{_g}", f"with {oracle_prefix(_g)} select src, dst, x.label as a, y.label as b{_more} from ge left join gv x on x.vid = src left join gv y on y.vid = dst")(
        lambda s, d, g=_g, more=_more: graph(s, d, g).edges.select("src", "dst", F.col("slabel").alias("a"), F.col("dlabel").alias("b"), *(["elabel"] if more else []))
    )
_TR = "with " + oracle_prefix("trade")
for _g in ("trade", "rmat_skewed"):
    _pre = "with " + oracle_prefix(_g)
    _n = "" if _g == "trade" else f"_{_g}"
    query(f"degree_stats{_n}", f"{_pre}, x as (select src, count(*) as d from ge group by src) select count(*) as vertices, cast(sum(d) as bigint) as directed_edges, max(d) as d_max, round(avg(d), 6) as d_avg, round(stddev_pop(d), 6) as d_std from x")(lambda s, d, g=_g: measures.degree_stats(graph(s, d, g).edges))
    query(f"degree_histogram{_n}", f"{_pre}, x as (select src, count(*) as degree from ge group by src) select degree, count(*) as n from x group by degree")(lambda s, d, g=_g: measures.degree_histogram(graph(s, d, g).edges))
query("degree_salted", f"{_TR} select src, count(*) as degree from ge group by src")(lambda s, d: layout.salted_degrees(graph(s, d, "trade").edges, 200))
query("label_histogram", f"{_TR} select label, count(*) as n from gv group by label")(lambda s, d: graph(s, d, "trade").vertices.groupBy("label").agg(F.count("*").alias("n")))
for _g in ("trade", "web"):
    query("label_pair_histogram" if _g == "trade" else "web_label_pairs", f"with {oracle_prefix(_g)} select x.label as a, y.label as b, count(*) as n from ge join gv x on x.vid = src join gv y on y.vid = dst where x.label is not null and y.label is not null group by 1, 2")(lambda s, d, g=_g: measures.label_pairs(graph(s, d, g)))
query("label_coverage", f"{_TR} select count(*) as vertices, count(*) filter (label in ('order:F', 'part:PROMO', 'supplier')) as covered from gv")(lambda s, d: measures.label_coverage(graph(s, d, "trade"), T2))
query("bfs_levels", f"""with recursive {_TR[5:]}, r(vid, level) as (select {1 << 40}::bigint, 0 union select ge.dst, r.level + 1 from r join ge on ge.src = r.vid where r.level < 3)
select vid, cast(min(level) as int) as level from r group by vid""")(lambda s, d: measures.bfs_levels(graph(s, d, "trade").edges, s.createDataFrame([(1 << 40,)], "vid long"), 3))  # fmt: skip
query("bfs_all_web", f"""with recursive {oracle_prefix('web')}, r(vid, level) as (select min(vid), 0 from gv where label = 'host' union select ge.dst, r.level + 1 from r join ge on ge.src = r.vid where r.level < 12)
select vid, cast(min(level) as int) as level from r group by vid""")(lambda s, d: measures.bfs_levels(graph(s, d, "web").edges, graph(s, d, "web").vertices.filter("label = 'host'").agg(F.min("vid").alias("vid"))))  # fmt: skip

# long chains and many small groups: events of a user that follow each other within two hours
_NEAR = "(select event_id, lead(event_id) over w as following, date_diff('second', ts, lead(ts) over w) as gap from events window w as (partition by user_id order by ts, event_id))"
query("components_chains", f"""with steps as (select user_id, event_id, ts, case when date_diff('second', lag(ts) over w, ts) <= 7200 then 0 else 1 end as begins from events window w as (partition by user_id order by ts, event_id)),
runs as (select user_id, event_id, sum(begins) over (partition by user_id order by ts, event_id) as run from steps) select event_id as node, min(event_id) over (partition by user_id, run) as component from runs""")(
    lambda s, d: (lambda e, w: connected_components(e.select("event_id", F.when(F.unix_seconds(F.lead(F.col("ts").cast("timestamp")).over(w)) - F.unix_seconds(F.col("ts").cast("timestamp")) <= 7200, F.lead("event_id").over(w)).otherwise(F.col("event_id")).alias("following")), "event_id", "following"))(table(s, d, "events"), W.partitionBy("user_id").orderBy("ts", "event_id"))
)
query("connected_components", f"""with recursive {oracle_prefix('docs')}, own as materialized (select src as doc, dst as source from ge where src < {14 << 40} and dst >= {14 << 40}),
tied as materialized (select distinct x.source as a, y.source as b from own x join ge on ge.src = x.doc join own y on y.doc = ge.dst union select source, source from own),
r(a, b) as (select a, b from tied union select r.a, tied.b from r join tied on tied.a = r.b), least as (select source, min(doc) as doc from own group by source),
top as (select r.a as source, min(least.doc) as component from r join least on least.source = r.b group by r.a)
select doc as node, component from own join top using (source) union all select source, component from top""")(
    # sources tie their documents together, copies tie sources: few components, a hub at each source
    lambda s, d: connected_components(graph(s, d, "docs").edges)
)
for _k in (3, 12):
    query(f"k_core_{_k}")(lambda s, d, k=_k: measures.k_core(graph(s, d, "coorder").edges, k))
query("k_core")(lambda s, d: measures.k_core(graph(s, d, "session").edges, 3))

# ---- relational operators ----------------------------------------------------------------------------------------------------------
for _n in relational.SQL:
    query(_n, relational.oracle_side(_n))(lambda s, d, n=_n: relational.spark_side(s, d, n))
# a join would shuffle every wedge
query("triangle_count", relational.oracle_side("triangle_count"))(lambda s, d: baselines.clique_grow(graph(s, d, "coorder").edges, 3).agg(F.count("*").alias("n")))


def _neighbours(s, d, label: str) -> DataFrame:
    return graph(s, d, "trade").edges.filter(F.col("slabel") == label)


query("join_semi", f"{_M2} select vid from gv where vid in (select r0 from m union select r1 from m union select r2 from m)")(lambda s, d: graph(s, d, "trade").vertices.join(solution(s, d, "w2").state.masks, "vid", "left_semi").select("vid"))
query("join_anti", f"{_M2} select vid from gv where vid not in (select r0 from m union select r1 from m union select r2 from m)")(lambda s, d: graph(s, d, "trade").vertices.join(solution(s, d, "w2").state.masks, "vid", "left_anti").select("vid"))
query("join_null_safe", "select d.doc_id, l.toxic from documents d join labels l on d.doc_id is not distinct from l.doc_id")(lambda s, d: (lambda x, y: x.join(y, x.doc_id.eqNullSafe(y.doc_id)).select(x.doc_id, y.toxic))(table(s, d, "documents"), table(s, d, "labels")))
for _n, _h in (("join_inner_broadcast", "broadcast"), ("join_shuffle_hash", "shuffle_hash"), ("join_sort_merge", "merge")):
    query(_n, f"{_TR}, l as materialized (select src, dst from ge join gv on vid = src and label = 'order:F'), r as materialized (select src, count(*) as n from ge join gv on vid = dst and label = 'supplier' group by src) select l.src as o, cast(sum(n) as bigint) as wedges from l join r on r.src = l.dst group by l.src")(
        lambda s, d, h=_h: (lambda e: e.filter("slabel = 'order:F'").select(F.col("src").alias("o"), F.col("dst").alias("mid")).join(e.filter("dlabel = 'supplier'").select(F.col("src").alias("mid"), "dst").hint(h), "mid").groupBy("o").agg(F.count("*").alias("wedges")))(graph(s, d, "trade").edges)
    )
query("join_asof", "select p.event_id as purchase, c.event_id as click from (select * from events where event_type = 'purchase') p asof join (select * from events where event_type = 'click') c on p.user_id = c.user_id and p.ts >= c.ts")(
    lambda s, d: table(s, d, "events").withColumn("click", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", F.col("event_type") != "click", "event_id").rowsBetween(W.unboundedPreceding, 0))).filter("event_type = 'purchase' and click is not null").select(F.col("event_id").alias("purchase"), "click")
)
query("agg_bitmask", f"{_TR} select src, bit_or(1::bigint << (dst >> 40)) as kinds, bit_and(dst >> 40) as common, bit_count(bit_or(1::bigint << (dst >> 40))) as n from ge where src >= {6 << 40} and src < {7 << 40} group by src")(
    lambda s, d: graph(s, d, "trade").edges.filter(f"src >= {6 << 40} and src < {7 << 40}").groupBy("src").agg(F.bit_or(F.expr("shiftleft(1L, cast(shiftright(dst, 40) as int))")).alias("kinds"), F.bit_and(F.shiftright("dst", 40)).alias("common")).withColumn("n", F.bit_count("kinds"))
)
_TYPES = ("click", "view", "purchase", "error", "signup")
query("agg_pivot", "select cast(ts as date)::varchar as day, " + ", ".join(f"count(*) filter (event_type = '{x}') as {x}" for x in _TYPES) + " from events group by 1")(lambda s, d: table(s, d, "events").groupBy(F.to_date("ts").cast("string").alias("day")).pivot("event_type", list(_TYPES)).count().na.fill(0, list(_TYPES)))
query("agg_collect", f"{_TR} select src, list_aggregate(list_sort(list_distinct(list(y.label))), 'string_agg', ',') as labels from ge join gv x on x.vid = src and x.label = 'supplier' join gv y on y.vid = dst group by src")(lambda s, d: _neighbours(s, d, "supplier").groupBy("src").agg(F.array_join(F.array_sort(F.collect_set("dlabel")), ",").alias("labels")))
query("agg_percentile", f"{_TR}, x as (select src, count(*) as d from ge group by src) select quantile_cont(d, 0.5) as median, quantile_cont(d, 0.9) as upper from x")(lambda s, d: graph(s, d, "trade").edges.groupBy("src").agg(F.count("*").alias("d")).agg(F.percentile("d", 0.5).alias("median"), F.percentile("d", 0.9).alias("upper")))
query("agg_approx_distinct")(lambda s, d: _neighbours(s, d, "supplier").groupBy("dlabel").agg(F.approx_count_distinct("dst").alias("n")))
query("sample_bernoulli")(lambda s, d: graph(s, d, "trade").vertices.sample(0.1, 7).select("vid"))
query("fn_json", "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")(lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
query("fn_array", f"{_TR} select src, len(list(dst)) as n, list_min(list(dst)) as least, list_max(list(dst)) as most, list_contains(list(dst), {2 << 40}) as first_nation from ge where src < {4 << 40} group by src")(
    lambda s, d: graph(s, d, "trade").edges.filter(f"src < {4 << 40}").groupBy("src").agg(F.collect_list("dst").alias("x")).select("src", F.size("x").cast("long").alias("n"), F.array_min("x").alias("least"), F.array_max("x").alias("most"), F.array_contains("x", F.lit(2 << 40)).alias("first_nation"))
)
query("fn_array_hof", "select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * x)), 4) as norm2, len(list_filter(embedding, lambda x: x > 0)) as positive from embeddings")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))
)
query("fn_explode", f"{_M2} select distinct vid, role from ({_mask_sql(T2)}) x")(lambda s, d: solution(s, d, "w2").vertices.select("vid", F.explode("roles").alias("role")))
query("fn_posexplode", f"{_M2} select src, dst, pos from (select r0 as src, r1 as dst, 0 as pos from m union select r1, r2, 1 from m) x")(lambda s, d: enumerate_matches(solution(s, d, "w2")).select(F.posexplode(F.array(F.struct(F.col("r0").alias("src"), F.col("r1").alias("dst")), F.struct(F.col("r1").alias("src"), F.col("r2").alias("dst")))).alias("pos", "e")).select("e.src", "e.dst", "pos").distinct())
query("fn_split", "select page_id, split_part(url, '/', 3) as host, len(string_split(url, '/')) as n from pages")(lambda s, d: table(s, d, "pages").select("page_id", F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.size(F.split("url", "/")).cast("long").alias("n")))
query("fn_href_extract", f"select page_id, unnest(regexp_extract_all(html, '{HREF}', 1)) as link from pages")(lambda s, d: table(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREF), 1)).alias("link")))
query("fn_domain_label", f"select page_id, {sql_domain_label('url')} as label, {sql_domain_label(chr(39) + 'http://www.ox.ac.uk/a' + chr(39))} as fixed from pages")(lambda s, d: table(s, d, "pages").select("page_id", domain_label("url").alias("label"), domain_label(F.lit("http://www.ox.ac.uk/a")).alias("fixed")))
query("fn_degree_label", f"{_TR} select src, 'd' || cast(ceil(log2(count(*) + 1)) as int) as label from ge group by src")(lambda s, d: graph(s, d, "trade").edges.groupBy("src").agg(F.count("*").alias("n")).select("src", degree_label("n").alias("label")))
query("fn_map", f"{_M2} select r0, r1, r2 from m")(lambda s, d: enumerate_matches(solution(s, d, "w2")).select(F.map_from_arrays(F.array(*[F.lit(q) for q in range(3)]), F.array("r0", "r1", "r2")).alias("m")).select(*[F.element_at("m", F.lit(q)).alias(f"r{q}") for q in range(3)]))
query("fn_struct", f"{_TR} select label, min(vid) as first, max(vid) as last from gv group by label")(lambda s, d: graph(s, d, "trade").vertices.groupBy("label").agg(F.min(F.struct("vid", "label")).alias("x"), F.max(F.struct("vid", "label")).alias("y")).select("label", F.col("x.vid").alias("first"), F.col("y.vid").alias("last")))
query("cte_recursive", f"with recursive {_TR[5:]}, r(vid, hop) as (select {1 << 40}::bigint, 0 union all select e.dst, hop + 1 from r join ge e on e.src = r.vid and e.dst >> 40 = hop + 2 where hop < 2) select vid, hop from r")(
    lambda s, d: s.sql(f"with recursive r(vid, hop) as (select {1 << 40}L, 0 union all select e.dst, hop + 1 from r join {{ge}} e on e.src = r.vid and shiftright(e.dst, 40) = hop + 2 where hop < 2) select vid, hop from r", ge=graph(s, d, "trade").edges)
)
query("sql_temp_view", f"{_M2} select r0, r1, r2 from m")(lambda s, d: _views(s, d))


def _views(s, d):
    """The triangle as a join over temporary views of the kept graph."""
    x = solution(s, d, "w2")
    x.state.vertices.createOrReplaceTempView("graphsieve_kept_v")
    x.edges.createOrReplaceTempView("graphsieve_kept_e")
    return s.sql("""select a.src as r0, a.dst as r1, b.dst as r2 from graphsieve_kept_e a join graphsieve_kept_e b on a.dst = b.src join graphsieve_kept_e c on c.src = a.src and c.dst = b.dst
        join graphsieve_kept_v x on x.vid = a.src and x.label = 'order:F' join graphsieve_kept_v y on y.vid = a.dst and y.label = 'part:PROMO' join graphsieve_kept_v z on z.vid = b.dst and z.label = 'supplier'""")


# ---- files and Python ----------------------------------------------------------------------------------------------------------------
def _through(spark, df, fmt: str, schema: str) -> DataFrame:
    path = new_path(spark, f"sink-{fmt}")
    df.write.format(fmt).save(path)
    return spark.read.schema(schema).format(fmt).load(path)


_UP = f"{_TR} select src, dst from ge where src < dst"
query("scan_csv_edges", _UP)(lambda s, d: _through(s, graph(s, d, "trade").edges.filter("src < dst").select("src", "dst"), "csv", "src long, dst long"))
query("scan_json_edges", _UP)(lambda s, d: _through(s, graph(s, d, "trade").edges.filter("src < dst").select("src", "dst"), "json", "src long, dst long"))
query("scan_orc_edges", _UP)(lambda s, d: _through(s, graph(s, d, "trade").edges.filter("src < dst").select("src", "dst"), "orc", "src long, dst long"))
query("scan_text_adjacency", _UP)(
    lambda s, d: _through(s, graph(s, d, "trade").edges.filter("src < dst").groupBy("src").agg(F.collect_list("dst").alias("n")).select(F.concat_ws(" ", F.col("src").cast("string"), F.array_join(F.transform("n", lambda x: x.cast("string")), " ")).alias("value")), "text", "value string").select(F.split("value", " ").alias("x")).select(F.element_at("x", 1).cast("long").alias("src"), F.explode(F.slice("x", F.lit(2), F.size("x") - 1)).alias("dst")).select("src", F.col("dst").cast("long"))
)


@query("scan_json_template", f"{_M2} {_edge_sql(T2)}")
def _template_file(s, d):
    """A template read from a JSON file and searched."""
    text = _through(s, s.createDataFrame([(T2.to_json(),)], "value string"), "text", "value string").first()[0]
    return sieve(graph(s, d, "trade"), Template.from_json(text)).edges


query("sink_snapshot", f"{_M2} {_edge_sql(T2)}")(lambda s, d: _through(s, solution(s, d, "w2").edges, "parquet", "src long, dst long"))
query("sink_bucketed", f"{_M2} {_edge_sql(T2)}")(lambda s, d: sinks.bucketed(solution(s, d, "w2").edges))
query("sink_partitioned", f"{_M2} select src, dst, cast(src >> 40 as int) as kind from ({_edge_sql(T2)}) x")(lambda s, d: sinks.partitioned(solution(s, d, "w2").edges))
query("udf_scalar_pandas", "select x.vec_id, round(list_cosine_similarity(x.embedding::double[], y.embedding::double[]), 4) as likeness from embeddings x join embeddings y on y.vec_id = x.vec_id + 1")(
    lambda s, d: (lambda e: e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other")), "vec_id").select("vec_id", F.round(cosine("embedding", "other"), 4).alias("likeness")))(table(s, d, "embeddings"))
)
query("udaf_grouped", f"{_M2}, near as (select e.src, e.dst, k.vid is not null as kept from ge e join gv x on x.vid = e.src and x.label = 'supplier' join gv y on y.vid = e.dst and y.label = 'part:PROMO' left join (select distinct r1 as vid, r2 as s from m) k on k.vid = e.dst and k.s = e.src) select src, round(count(*) filter (kept) / count(*), 6) as likeness from near group by src")(
    # how alike a supplier's PROMO parts in the graph and in the answer are
    lambda s, d: (lambda e, k: e.join(k, ["src", "dst"], "left").groupBy("src").agg(F.round(jaccard("dst", "kept"), 6).alias("likeness")))(graph(s, d, "trade").edges.filter("slabel = 'supplier' and dlabel = 'part:PROMO'").select("src", "dst"), solution(s, d, "w2").edges.select("src", "dst", F.col("dst").alias("kept")))
)
query("map_in_pandas", f"{_TR} select vid, split_part(label, ':', 1) as kind, split_part(label, ':', 2) as detail from gv")(lambda s, d: graph(s, d, "trade").vertices.select("vid", "label").mapInPandas(bucketed_labels, "vid long, kind string, detail string"))
query("apply_in_pandas", f"with {oracle_prefix('session')}, u as (select e.src as component, e.dst as vid from ge e where e.src >> 40 = 8), t as (select a.component, count(*) as triangles from u a join ge e on e.src = a.vid join u b on b.component = a.component and b.vid = e.dst and a.vid < b.vid group by 1) select u.component, coalesce(max(t.triangles), 0) as triangles from u left join t on t.component = u.component group by 1")(
    # a user with its events is a component of its own: triangles by backtracking in it
    lambda s, d: (lambda e, own: own.join(e, "src").select("component", "src", "dst").unionByName(own.select("component", F.col("src"), F.col("component").alias("dst"))).unionByName(own.select("component", F.col("component").alias("src"), F.col("src").alias("dst"))).distinct().groupBy("component").applyInPandas(triangles_of, "component long, triangles long"))(
        graph(s, d, "session").edges.filter("slabel <> 'user' and dlabel <> 'user'").select("src", "dst"), graph(s, d, "session").edges.filter("slabel = 'user'").select(F.col("src").alias("component"), F.col("dst").alias("src"))
    )
)
query("udtf_relaxations")(lambda s, d: Relaxations(F.lit(CLIQUE4[1].to_json()), F.lit(3)))

# ---- streams, run over files of events; batch answers are the oracles ---------------------------------------------------------------
_STAMP = "strftime({x}, '%Y-%m-%d %H:%M:%S')"


def _files(s, d, parts: int = 8) -> str:
    path = new_path(s, "events")
    table(s, d, "events").repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def _replayed(s, d, files: int = 8):
    return streams.read_events(s, once(s, d, ("replay",), lambda: _files(s, d)), files)


def _stamped(df):
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


def _timed(s, d):
    return table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


_HOURS = f"select {_STAMP.replace('{x}', 'time_bucket(interval 1 hour, ts)')} as start, event_type, count(*) as n from events group by 1, 2"
query("tumbling_counts", _HOURS)(lambda s, d: _stamped(streams.tumbling(_timed(s, d))))
query("stream_tumbling", _HOURS)(lambda s, d: _stamped(streams.run_to_table(streams.tumbling(_replayed(s, d), late="60 days"), "complete")))
query("sliding_counts", f"select {_STAMP.replace('{x}', 'start')} as start, count(*) as n from (select time_bucket(interval 15 minutes, ts) - k * interval 15 minutes as start from events, (select unnest([0, 1, 2, 3]) as k)) x group by 1")(lambda s, d: _stamped(streams.sliding(_timed(s, d))))
query("session_counts", f"""select user_id, {_STAMP.replace('{x}', 'min(ts)')} as start, count(*) as n from (select user_id, ts, sum(begins) over (partition by user_id order by ts, event_id) as run
from (select user_id, ts, event_id, case when lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes > ts then 0 else 1 end as begins from events) x) y group by user_id, run""")(lambda s, d: _stamped(streams.sessions(_timed(s, d))))  # fmt: skip
query("stream_dedup", "select event_id from events")(lambda s, d: streams.run_to_table(streams.deduplicated(_replayed(s, d), late="60 days").select("event_id")))
query("stream_interval", "select c.user_id, c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 30 minutes")(lambda s, d: streams.run_to_table(streams.clicks_to_purchases(_replayed(s, d), late="60 days")))
query("stream_edges", f"select event_id as a, following as b from {_NEAR} x where following is not null")(lambda s, d: streams.run_to_table(streams.following_edges(_replayed(s, d, files=8))))


@query("stream_late", "select count(*) as read from events")
def _late(s, d):
    """The rows that a watermarked query read (all of them); what it dropped as late is told by ``stream_late_dropped``."""
    return s.createDataFrame([(_late_run(s, d)["rows"],)], "read long")


@query("stream_late_dropped")
def _late_dropped(s, d):
    x = _late_run(s, d)
    return s.createDataFrame([(x["dropped"], x["batches"])], "dropped long, batches long")


def _late_run(s, d) -> dict:
    """Files in the order of time but for one in twenty rows, which comes in the last: those are late."""

    def run():
        path = new_path(s, "late")
        e = table(s, d, "events").withColumn("_late", F.pmod(F.col("event_id"), F.lit(20)) == 0)
        for k, part in enumerate((e.filter("not _late"), e.filter("_late"))):
            part.drop("_late").coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(f"{path}/step={k}")
        spark_read = s.readStream.schema(streams.SCHEMA + ", step int").option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
        return streams.late_rows(spark_read)[1]

    return once(s, d, ("late",), run)


@query("stream_matches", f"{oracle_matches('session', WORKLOADS['w3'][1])} select r0, r1, r2, r3 from m")
def _matches_of_batches(s, d):
    """Edges come in three batches; every match is found in the batch that completes it."""
    g = graph(s, d, "session")
    up = materialize(g.edges.filter("src < dst").select("src", "dst"), "stream-edges")
    parts = [up.filter(F.pmod("src", F.lit(3)) == k).select("src", "dst") for k in range(3)]
    return streams.match_stream(parts, g.vertices, WORKLOADS["w3"][1])


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagship: the exact vertices and roles of the order-part-supplier triangle."""
    return solution(spark, sf_dir, "w2").vertices.select("vid", "label", "mask")


__all__ = ["ORACLES", "QUERIES", "entry", "fill", "query"]
