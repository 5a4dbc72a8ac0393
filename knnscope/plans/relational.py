"""Relational operators round the methods, as SQL that Spark and DuckDB run alike. Braces name tables."""

from __future__ import annotations

from knnscope.sources.views import LINE1D, LISTINGS, PHOTOS, SHAPES, SHAPES_B, STATIONS, VIEWS, WEDGE


def snap(v: str, digits: int = 3) -> str:
    m = f"1{'0' * digits}e0"
    return f"floor({m}*({v})+0.5e0)/{m}"


S, L, P, T, N = (f"({v})" for v in (SHAPES, LISTINGS, PHOTOS, STATIONS, LINE1D))
CELL = "cast(floor(({c}+0.0005e0)/{s}e0) as bigint)"
_CX, _CY = CELL.format(c="x", s=16), CELL.format(c="y", s=16)
DENSE = f"select cx, cy, n from (select {_CX} cx, {_CY} cy, count(*) n from {S} s group by 1, 2) g where n >= 14"
GRID_LABEL = f"select id, case when lab='error' then null else lab end truth, case when n >= 14 then cx*1000+cy end pred from (select id, lab, cx, cy, count(*) over (partition by cx, cy) n from (select id, lab, {_CX} cx, {_CY} cy from {S} s) a) b"
STATION_LABEL = (
    f"select id, truth, case when n >= 3 then cx*1000+cy end pred from (select id, truth, cx, cy, count(*) over (partition by cx, cy) n from (select id, "
    f"case when id%10 < 6 then 'centre' when id%10 < 9 then 'outer' end truth, {CELL.format(c='x', s=8)} cx, {CELL.format(c='y', s=8)} cy from {T} s) a) b"
)

QUERIES: dict[str, str] = {f"view_{n}": (f"select id, lab, x, y from ({v})" if n in ("shapes", "shapes_b", "shapes_c") else f"select id, x, y from ({v})" if n not in ("line1d",) else v) for n, v in VIEWS.items() if n != "wedge"}
QUERIES |= {
    "scan_projected": f"select id, x, {snap('y')} y from ({WEDGE})",
    "scan_filtered_bbox": f"select id, x, {snap('y')} y from ({WEDGE}) where x between 10 and 20 and y between 10 and 30",
    "scan_circle": f"select id, x, y from {S} s where (x-200)*(x-200)+(y-320)*(y-320) <= 2500",
    "filter_price_priority": f"select id, price, pri, x, y from {L} l where price between 100000 and 200000 and pri in ('1-URGENT','2-HIGH')",
    "filter_like_nullsafe": "select p_partkey, p_name from {part} where p_type like '%BRASS%' or p_name is null",
    # cells and runs
    "cells_1d": f"select {CELL.format(c='x', s=5)} cx, count(*) n from {N} l group by 1",
    "cells_2d": f"select {_CX} cx, {_CY} cy, count(*) n from {S} s group by 1, 2",
    "cells_dense_1d": f"select cx, n from (select {CELL.format(c='x', s=5)} cx, count(*) n from {N} l group by 1) g where n >= 60",
    "cells_dense_2d": DENSE,
    "runs_dense_1d": f"select min(cx) lo, max(cx) hi from (select cx, cx - row_number() over (order by cx) run from (select {CELL.format(c='x', s=5)} cx, count(*) n from {N} l group by 1) g where n >= 60) r group by run",
    # reports of the experiments
    "heatmap_2d": f"select {CELL.format(c='x', s=50)} hx, {CELL.format(c='y', s=50)} hy, count(*) n from {P} p group by 1, 2",
    "top_tags_per_cluster": f"select spot, tag, n, r from (select spot, tag, n, row_number() over (partition by spot order by n desc, tag) r from (select id%16 spot, regexp_extract(props, '\"k\": *([0-9]+)', 1) tag, count(*) n from {P} p group by 1, 2) a) b where r <= 3",
    "price_stats_by_cluster": f"select reg, count(*) n, {snap('avg(price)', 1)} mean_price, {snap('stddev(price)', 1)} sd_price, min(price) low, max(price) high from {L} l group by reg",
    "price_hist_counts": f"select cast(floor(price/50000) as bigint) bin, reg, count(*) n from {L} l group by 1, 2",
    "price_hist_pivot": f"select cast(floor(price/50000) as bigint) bin, " + ", ".join(f"sum(case when reg={r} then 1 else 0 end) reg{r}" for r in range(5)) + f" from {L} l group by 1",
    "clusters_ge_100": f"select reg, nat, count(*) n from {L} l group by reg, nat having count(*) >= 100",
    "small_pooled": f"select case when n >= 620 then nat else -1 end grp, sum(n) n from (select nat, count(*) n from {L} l group by nat) a group by 1",
    "catalogues_common": f"select id from {L} a where id%7 <> 0 intersect select id from {L} b where id%7 <> 1",
    "catalogues_only_a": f"select id from {L} a where id%7 <> 0 except select id from {L} b where id%7 <> 1",
    "catalogues_only_b": f"select id from {L} a where id%7 <> 1 except select id from {L} b where id%7 <> 0",
    "catalogue_agreement": f"select a.reg rega, b.reg regb, count(*) n from (select * from {L} l where id%7 <> 0) a join (select * from {L} m where id%7 <> 1) b on a.id = b.id group by 1, 2",
    "hour_profile_by_cluster": f"select grp, h, n, {snap('n / cast(max(n) over (partition by grp) as double)')} share from (select case when id%10 < 6 then 0 else id%10 end grp, hour(ts) h, count(*) n from {T} s join {{events}} e on e.user_id = s.id group by 1, 2) a",
    "noise_share_counts": "select p, count(*) n from (select * from " + S + " s) s cross join (select 0 p union all select 25 union all select 50 union all select 75 union all select 100) q where lab <> 'error' or (id*31+7)%100 < p group by p",
    "prior_weights": "select n_nationkey, n_regionkey, count(*) w from {customer} join {nation} on c_nationkey = n_nationkey group by 1, 2",
    # joins
    "join_hash": "select n_name, count(*) n from {customer} join {nation} on c_nationkey = n_nationkey group by n_name",
    "join_merge": "select o_orderkey, count(*) lines from {orders} join {lineitem} on o_orderkey = l_orderkey group by o_orderkey",
    "join_broadcast": "select s_suppkey, r_name from {supplier} join {nation} on s_nationkey = n_nationkey join {region} on n_regionkey = r_regionkey",
    "join_theta": "select a.n_nationkey x, b.n_nationkey y from {nation} a join {nation} b on a.n_nationkey < b.n_nationkey and a.n_regionkey = b.n_regionkey",
    "join_semi": "select c_custkey from {customer} left semi join {orders} on c_custkey = o_custkey",
    "join_anti": "select c_custkey from {customer} left anti join {orders} on c_custkey = o_custkey",
    "join_full": "select coalesce(a.id, b.id) id, a.id is null only_b, b.id is null only_a from (select id from " + T + " s where id%7 <> 0) a full join (select id from " + T + " u where id%7 <> 1) b on a.id = b.id",
    "labelled_documents": "select d.source, count(*) n, sum(l.quality) good from {documents} d join {labels} l on d.doc_id = l.doc_id group by d.source",
    # aggregates
    "agg_distinct": f"select reg, count(distinct nat) nats, count(distinct pri) pris from {L} l group by reg",
    "agg_having": "select l_returnflag, l_linestatus, count(*) n, sum(l_quantity) q from {lineitem} group by 1, 2 having count(*) > 100",
    "agg_rollup": f"select reg, nat, count(*) n from {L} l group by rollup(reg, nat)",
    "agg_cube": f"select reg, pri, count(*) n from {L} l group by cube(reg, pri)",
    "agg_grouping_sets": f"select reg, pri, nat, count(*) n from {L} l group by grouping sets ((reg, pri), (nat), ())",
    "agg_mode": "select user_id, event_type, n from (select user_id, event_type, n, row_number() over (partition by user_id order by n desc, event_type) r from (select user_id, event_type, count(*) n from {events} group by 1, 2) a) b where r = 1",
    "agg_max_by": "select o_custkey, max(o_totalprice) top, max_by(o_orderkey, o_totalprice) of from {orders} group by o_custkey",
    "agg_filtered": "select user_id, count(*) filter (where event_type = 'click') clicks, count(*) n from {events} group by user_id",
    # windows
    "win_rank_family": "select c_custkey, row_number() over w rn, rank() over w rk, dense_rank() over w dr from {customer} window w as (partition by c_nationkey order by c_acctbal desc, c_custkey)",
    "win_lag_gaps": "select event_id, datediff(ts, prev) gap from (select event_id, ts, lag(ts) over (partition by user_id order by ts, event_id) prev from {events}) a" ,
    "win_rows_frame": "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row) n from {orders}",
    "win_range_frame": "select l_orderkey, l_linenumber, count(*) over (partition by l_suppkey order by l_quantity range between 5 preceding and 5 following) n from {lineitem}",
    "win_ntile": "select c_custkey, ntile(4) over (partition by c_mktsegment order by c_acctbal, c_custkey) q from {customer}",
    "win_percent_rank": f"select c_custkey, {snap('percent_rank() over (partition by c_nationkey order by c_acctbal)', 6)} pr from {{customer}}",
    "win_conversation_turns": "select conv_id, turn, role, coalesce(lag(role) over (partition by conv_id order by turn), '') before from {conversations}",
    "topk_sort": "select l_orderkey, l_linenumber, l_extendedprice from {lineitem} order by l_extendedprice desc, l_orderkey, l_linenumber limit 50",
    "limit_per_group": "select c_nationkey, c_custkey from (select c_nationkey, c_custkey, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) r from {customer}) a where r <= 3",
    # sets
    "set_union": "select c_nationkey k from {customer} union select s_nationkey from {supplier}",
    "set_intersect": "select c_nationkey k from {customer} intersect select s_nationkey from {supplier}",
    "set_except": "select n_nationkey k from {nation} except select s_nationkey from {supplier}",
    "set_distinct": "select distinct source, lang from {documents}",
    "set_shared_text": "select text from {documents} intersect select text from {documents} where doc_id % 2 = 0",
    # functions
    "fn_string": "select p_partkey, upper(p_brand) b, length(p_name) n, substring(p_type, 1, 5) t, replace(p_name, ' ', '_') r, concat_ws('|', p_brand, p_type) c from {part}",
    "fn_date": "select o_orderkey, year(o_orderdate) y, month(o_orderdate) m, day(o_orderdate) d, datediff(date_trunc('month', o_orderdate), cast('1970-01-01' as timestamp)) as days from {orders}",
    "fn_math": f"select l_orderkey, l_linenumber, {snap('sqrt(l_extendedprice)')} r, {snap('ln(l_quantity)')} ln, greatest(l_quantity, 10e0) g, cast(floor(l_quantity/7) as bigint) f from {{lineitem}}",
    "fn_json": "select event_id, cast(regexp_extract(props, '\"k\": *([0-9]+)', 1) as int) k from {events}",
    "fn_url": "select page_id, regexp_extract(url, '^([a-z]+)://', 1) scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) host from {pages}",
    "subquery_scalar": "select c_custkey, c_acctbal from {customer} where c_acctbal > (select avg(c_acctbal) + 1000 from {customer})",
    "subquery_correlated": "select o_orderkey from {orders} o where o_totalprice = (select max(o_totalprice) from {orders} i where i.o_custkey = o.o_custkey)",
    "sample_hash": "select event_id from {events} where (event_id*2654435761)%1000 < 100",
    "lower_bounds": f"select (select count(*) from {S} s) n, sum(n) dense_points, count(*) dense_cells from ({DENSE}) d",
}
#: Where the SQL leaves a tie open, Spark is told which row to take: the first of the table, as DuckDB does.
SPARK = {
    "agg_max_by": "select o_custkey, max(o_totalprice) top, max_by(o_orderkey, case when o_orderkey is not null and o_totalprice is not null "
    "then struct(o_totalprice, -o_orderkey) end) of from {orders} group by o_custkey",
}
#: DuckDB says some things differently; everything else runs unchanged.
DIALECT = {
    "left semi join": "semi join",
    "left anti join": "anti join",
    "datediff(": "datediff('day', ",
    "cast('1970-01-01' as timestamp)": "timestamp '1970-01-01'",
}
SWAPPED = {
    "win_lag_gaps": "select event_id, datediff('day', prev, ts) gap from (select event_id, ts, lag(ts) over (partition by user_id order by ts, event_id) prev from events) a",
    "fn_date": "select o_orderkey, year(o_orderdate) y, month(o_orderdate) m, day(o_orderdate) d, datediff('day', date '1970-01-01', date_trunc('month', o_orderdate)) as days from orders",
}
__all__ = ["DENSE", "GRID_LABEL", "QUERIES", "SHAPES_B"]
