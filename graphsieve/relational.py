"""Relational operators on graphs and kept graphs, told once in SQL that runs on both engines.

``{gv}`` and ``{ge}`` are a graph's vertices (vid, label) and edges (src, dst); ``{kv}`` and ``{ke}`` those of the triangle's answer on it, ``{hv}`` the
vertices of the shared-edge cycles' answer. Spark reads the library's tables; the oracle makes its own from the given ones.
"""

from __future__ import annotations

from graphsieve.sources.graphs import TABLES, oracle_matches, oracle_prefix
from graphsieve.workloads import WORKLOADS, graph, solution, table

_DEGREES = "(select src, count(*) as d from {ge} group by src)"
#: key: statement; on the trade graph unless named in ON.
SQL: dict[str, str] = {
    "scan_prune_filter": "select o_orderkey, o_totalprice from {orders} where o_orderstatus = 'F' and o_totalprice > 300000",
    "symmetric_edges": "select count(*) as directed, count(b.src) as returned from {ge} a left join {ge} b on a.src = b.dst and a.dst = b.src",
    "join_left": "select v.vid, count(e.dst) as degree from {gv} v left join {ge} e on e.src = v.vid group by v.vid",
    "join_right": "select v.vid, count(e.dst) as degree from {ke} e right join {kv} v on e.src = v.vid group by v.vid",
    "join_full": "select coalesce(k.vid, h.vid) as vid, case when k.vid is null then 0 else 1 end as triangle, case when h.vid is null then 0 else 1 end as cycles from {kv} k full join {hv} h on k.vid = h.vid",
    "join_cross": "select a.label as a, b.label as b from (select distinct label from {gv}) a cross join (select distinct label from {gv}) b",
    "join_theta": "select x.src as a, y.src as b from {ge} x join {ge} y on x.dst = y.dst and x.src < y.src join {gv} n on n.vid = x.dst and n.label = 'nation' join {gv} s on s.vid = x.src and s.label = 'supplier' join {gv} u on u.vid = y.src and u.label = 'supplier'",
    "join_range": "select a.event_id as a, b.event_id as b from {events} a join {events} b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 5 minutes",
    "join_interval_orders": "select l_orderkey, count(*) as n from {lineitem} join {orders} on l_orderkey = o_orderkey and l_shipdate between o_orderdate and o_orderdate + interval 30 days group by l_orderkey",
    "agg_basic": f"select v.label, count(*) as n, cast(sum(d) as bigint) as total, min(d) as lo, max(d) as hi, round(avg(d), 4) as mean from {_DEGREES} x join {{gv}} v on v.vid = x.src group by v.label",
    "agg_filter": "select count(*) as n, count(*) filter (where label = 'supplier') as suppliers, count(*) filter (where label like 'order:%') as orders from {kv}",
    "agg_distinct": "select count(*) as n, count(distinct l_orderkey) as orders from (select distinct l_orderkey, l_partkey from {lineitem}) x",
    "agg_having": "select src, count(*) as degree from {ge} group by src having count(*) >= 200",
    "agg_rollup": "select kind, label, count(*) as n, count(kept) as kept from (select v.vid >> 40 as kind, v.label, k.vid as kept from {gv} v left join {kv} k on k.vid = v.vid) x group by rollup(kind, label)",
    "agg_cube": "select label, kept, count(*) as n from (select v.label, case when k.vid is null then 'gone' else 'kept' end as kept from {gv} v left join {kv} k on k.vid = v.vid) x group by cube(label, kept)",
    "agg_grouping_sets": "select label, kept, count(*) as n, grouping(label) + 0 as over_labels from (select v.label, case when k.vid is null then 'gone' else 'kept' end as kept from {gv} v left join {kv} k on k.vid = v.vid) x group by grouping sets ((label), (kept), ())",
    "win_rank": f"select src, rank() over (partition by v.label order by d desc) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src where v.label like 'part:%'",
    "win_dense_rank": f"select src, dense_rank() over (partition by v.label order by d desc) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src where v.label like 'part:%'",
    "win_row_number": f"select src, row_number() over (partition by v.label order by d desc, src) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src where v.label like 'part:%'",
    "win_ntile": f"select src, ntile(4) over (partition by v.label order by d, src) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src where v.label like 'cust:%'",
    "win_percent_rank": f"select src, round(percent_rank() over (partition by v.label order by d), 6) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src where v.label like 'part:%'",
    "win_cume_dist": f"select src, round(cume_dist() over (partition by v.label order by d), 6) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src where v.label like 'part:%'",
    "win_lead_lag": "select event_id, lead(event_id) over (partition by user_id order by ts, event_id) as following, lag(event_id) over (partition by user_id order by ts, event_id) as earlier from {events}",
    "win_first_last": "select event_id, first_value(event_id) over (partition by user_id order by ts, event_id) as f, last_value(event_id) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as l from {events}",
    "win_nth": "select event_id, nth_value(event_id, 3) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as third from {events}",
    "win_running": "select src, dst, cast(sum(1) over (partition by src order by dst rows between unbounded preceding and current row) as bigint) as running, count(*) over (partition by src) as whole from {ke} where src >= " + str(4 << 40) + " and src < " + str(5 << 40),
    "win_rows_frame": "select event_id, count(*) over (partition by user_id order by ts, event_id rows between 3 preceding and 1 preceding) as x from {events}",
    "win_range_frame": "select event_id, count(*) over (partition by user_id order by ts range between interval 1 hour preceding and current row) as x from {events}",
    "sort_multi": f"select v.label, src, d from {_DEGREES} x join {{gv}} v on v.vid = x.src order by v.label, d desc, src limit 200",
    "limit_topk": f"select src, d from {_DEGREES} x order by d desc, src limit 20",
    "topk_per_group": f"select label, src, d from (select v.label, src, d, row_number() over (partition by v.label order by d desc, src) as k from {_DEGREES} x join {{gv}} v on v.vid = x.src) y where k <= 3",
    "sort_nulls": "select d.doc_id, quality from {documents} d left join {labels} l on d.doc_id = l.doc_id order by quality desc nulls last, d.doc_id limit 50",
    "set_union": "select vid from {kv} union select vid from {hv}",
    "set_union_all": "select vid from {kv} union all select vid from {hv}",
    "set_intersect": "select vid from {kv} intersect select vid from {hv}",
    "set_except": "select vid from {kv} except select vid from {hv}",
    "set_except_all": "select src as vid from {ke} except all select vid from {kv}",
    "set_intersect_all": "select src as vid from {ke} intersect all select vid from {hv}",
    "fn_string": "select p_partkey, upper(p_brand) as b, substr(p_name, 1, 5) as s, length(p_name) as n, concat(p_type, '-', p_brand) as c, lower(trim(p_name)) as t from {part}",
    "fn_regex": "select page_id, regexp_extract(url, '//([^/]+)', 1) as host, regexp_replace(url, '[?#].*$', '') as bare from {pages}",
    "fn_hash_md5": "select vid, md5(label) as h from {gv}",
    "fn_date": "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, cast(date_trunc('month', o_orderdate) as date) as first, cast(cast('1999-01-01' as date) as date) as fixed from {orders}",
    "fn_math": f"select src, cast(ceil(log2(d + 1)) as bigint) as degree_class, abs(d - 10) as off, d % 7 as r, round(sqrt(d), 6) as root from {_DEGREES} x",
    "fn_bits": "select vid, vid & 1099511627775 as own, vid >> 40 as kind, bit_count(vid) as ones, (vid >> 40) | 16 as flagged from {gv}",
    "fn_case": f"select src, case when d >= 100 then 'hub' when d > 1 then 'inner' else 'leaf' end as band from {_DEGREES} x",
    "fn_coalesce": "select d.doc_id, coalesce(quality, -1) as q, nullif(coalesce(quality, 0), 0) as z from {documents} d left join {labels} l on d.doc_id = l.doc_id",
    "fn_try_cast": "select page_id, try_cast(regexp_extract(url, '([0-9]+)', 1) as bigint) as n from {pages}",
    "fn_cast_decimal": f"select cast(sum(cast(d as decimal(38,0)) * d) as decimal(38,0)) as squares from {_DEGREES} x",
    "sub_exists": "select vid from {gv} v where label = 'supplier' and exists (select 1 from {ke} e where e.src = v.vid)",
    "sub_not_exists": "select vid from {gv} v where label = 'supplier' and not exists (select 1 from {ke} e where e.src = v.vid)",
    "sub_in": "select src, dst from {ge} where src in (select vid from {kv}) and dst in (select vid from {kv})",
    "sub_scalar": f"select count(*) as n from {_DEGREES} x where d > (select avg(d) from {_DEGREES} y)",
    "sub_lateral": "select v.vid, near.dst from {kv} v, lateral (select min(e.dst) as dst from {ke} e where e.src = v.vid) near where v.label = 'supplier'",
    "cte_plain": f"select d, count(*) as vertices from {_DEGREES} x group by d",
    "wedge_count": f"select cast(sum(d * (d - 1) / 2) as bigint) as wedges from {_DEGREES} x",
    "triangle_count": "select count(*) as n from {ge} a join {ge} b on a.dst = b.src and a.src < a.dst and b.src < b.dst join {ge} c on c.src = a.src and c.dst = b.dst",
    "square_count": "select cast(sum(n * (n - 1) / 2) as bigint) as n from (select a.src as x, b.dst as y, count(*) as n from {ge} a join {ge} b on a.dst = b.src and a.src < b.dst group by 1, 2) w",
    "lattice_edges": "select src, dst from {ge} where src < dst",
    "rmat_edges": "select src, dst from {ge}",
    "random_labels": "select label, count(*) as n from {gv} group by label",
    "sample_hash": "select vid from {gv} where substr(md5(cast(vid as varchar(20))), 1, 1) = '0'",
}
ON = {"triangle_count": "coorder", "square_count": "conv", "wedge_count": "coorder", "lattice_edges": "lattice", "rmat_edges": "rmat_skewed", "random_labels": "random50"}


def _part(t, mapped: str) -> str:
    return " union ".join(f"select r{q} as vid, '{x}' as label from {mapped}" for q, x in enumerate(t.labels))


def spark_side(spark, sf_dir: str, name: str):
    sql, g = SQL[name], ON.get(name, "trade")
    tables = {t: (lambda t=t: table(spark, sf_dir, t)) for t in TABLES}
    tables |= {
        "gv": lambda: graph(spark, sf_dir, g).vertices, "ge": lambda: graph(spark, sf_dir, g).edges.select("src", "dst"),
        "kv": lambda: solution(spark, sf_dir, "w2").state.vertices, "ke": lambda: solution(spark, sf_dir, "w2").edges, "hv": lambda: solution(spark, sf_dir, "w6").state.vertices,
    }
    return spark.sql(sql, **{t: make() for t, make in tables.items() if "{" + t + "}" in sql})


def oracle_side(name: str) -> str:
    sql, g = SQL[name], ON.get(name, "trade")
    plain = sql.format(**{t: t for t in [*TABLES, "gv", "ge", "kv", "ke", "hv"]})
    two, six = WORKLOADS["w2"][1], WORKLOADS["w6"][1]
    if "{kv}" in sql or "{ke}" in sql or "{hv}" in sql:
        pre, more = oracle_matches(g, two), []
        kept = " union ".join(f"select r{a} as src, r{b} as dst from m union select r{b}, r{a} from m" for a, b in two.edges)
        more = [f"kv as materialized ({_part(two, 'm')})", f"ke as materialized ({kept})"]
        if "{hv}" in sql:
            more += [oracle_matches(g, six, "h").split(oracle_prefix(g) + ", ", 1)[1], f"hv as materialized ({_part(six, 'h')})"]
        return f"{pre}, {', '.join(more)} {plain}"
    return f"with {oracle_prefix(g)} {plain}" if "{gv}" in sql or "{ge}" in sql else plain
