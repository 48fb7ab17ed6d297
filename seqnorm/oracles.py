"""What the queries should give, in SQL written from the definitions."""

from __future__ import annotations

import math

from seqnorm.operators.inject import CONCEPTS

# -- series ------------------------------------------------------------------------------------------


def _grid(table: str, ts: str, value: str, unit: str) -> str:
    return f"""
        g as (select unnest(generate_series(date_trunc('{unit}', (select min({ts}) from {table})), date_trunc('{unit}', (select max({ts}) from {table})), interval 1 {unit})) as ts),
        s as (select date_trunc('{unit}', {ts}) as ts, round(sum({value}), 2) as x from {table} group by 1),
        raw as (select cast(row_number() over (order by g.ts) - 1 as bigint) as pos, s.x from g left join s on g.ts = s.ts)"""


HOURLY = f"with {_grid('events', 'ts', 'value', 'hour')}, pts as (select pos, coalesce(x, 0) as x from raw)"
DAILY = f"with {_grid('lineitem', 'l_shipdate', 'l_extendedprice', 'day')}, pts as (select pos, coalesce(x, 0) as x from raw)"
ORDERS = f"with {_grid('orders', 'o_orderdate', 'o_totalprice', 'day')}, pts as (select pos, coalesce(x, 0) as x from raw)"


def _keyed(key: str, order: str, value: str, table: str) -> str:
    return f"select cast({key} as varchar) as series_id, cast(row_number() over (partition by {key} order by {order}) - 1 as bigint) as pos, round(cast({value} as double), 4) as x from {table}"


def _sources() -> dict[str, str]:
    fill = {
        "zero": "select pos, round(coalesce(x, 0), 4) as x from raw",
        "ffill": "select pos, round(last_value(x ignore nulls) over (order by pos), 4) as x from raw",
        "linear": """, e as (select pos, x, last_value(x ignore nulls) over (order by pos) as a, last_value(case when x is not null then pos end ignore nulls) over (order by pos) as pa,
              first_value(x ignore nulls) over (order by pos rows between current row and unbounded following) as b,
              first_value(case when x is not null then pos end ignore nulls) over (order by pos rows between current row and unbounded following) as pb from raw)
            select pos, round(case when x is not null then x when a is null or b is null then coalesce(a, b) else a + (b - a) * (pos - pa) / (pb - pa) end, 4) as x from e""",
    }
    head = f"with {_grid('orders', 'o_orderdate', 'o_totalprice', 'day')}"
    return {
        "points_events": "select 'events' as series_id, event_id as pos, round(value, 4) as x from events",
        "points_hourly": f"{HOURLY} select 'hourly' as series_id, pos, round(x, 4) as x from pts",
        "points_daily_lineitem": f"{DAILY} select 'daily_lineitem' as series_id, pos, round(x, 4) as x from pts",
        "points_daily_orders": f"{ORDERS} select 'daily_orders' as series_id, pos, round(x, 4) as x from pts",
        "points_by_type": _keyed("event_type", "event_id", "value", "events"),
        "points_by_user": _keyed("user_id", "event_id", "value", "events"),
        "points_doc_len": _keyed("'documents'", "doc_id", "n_chars", "documents"),
        "points_page_len": _keyed("'pages'", "page_id", "length(html)", "pages"),
        "points_turn_len": _keyed("conv_id", "turn", "length(text)", "conversations"),
        **{f"gapfill_hourly_{k}": f"with {_grid('events', 'ts', 'value', 'hour')}{'' if v.startswith(',') else ' '}{v}" for k, v in fill.items()},
        **{f"gapfill_orders_{k}": f"{head}{'' if v.startswith(',') else ' '}{v}" for k, v in fill.items()},
    }


# -- windows and distances ---------------------------------------------------------------------------


def _windows(ell: int) -> str:
    return f"w as (select a.pos as start, b.pos - a.pos as i, b.x from pts a join pts b on b.pos between a.pos and a.pos + {ell - 1} where a.pos + {ell - 1} <= (select max(pos) from pts))"


def _segments(length: int) -> str:
    return f"""seg as (select cast(floor(pos / {length}) as int) as seg, pos % {length} as i, x, x - avg(x) over (partition by floor(pos / {length})) as v
        from pts where pos < {length} * floor((select count(*) from pts) / {length}))"""


EMB = """with v as (select vec_id, unnest(range(1, 65)) as i, cast(unnest(embedding) as double) as x from embeddings where vec_id < {n}),
    c as (select vec_id, i, x - avg(x) over (partition by vec_id) as v from v),
    z as (select vec_id, i, v / stddev_pop(v) over (partition by vec_id) as z, v from c)"""


def _distances() -> dict[str, str]:
    pair = "select a.vec_id as a, b.vec_id as b, round(sqrt(sum((a.{c} - b.{c}) ** 2)), 4) as dist from z a join z b on a.i = b.i and a.vec_id < b.vec_id group by 1, 2"
    day = """select a.seg as a, b.seg as b, round(sqrt(sum((a.{c} - b.{c}) ** 2)), 4) as dist from q a join q b on b.seg = a.seg + 1 and a.i = b.i group by 1, 2"""
    days = f"{HOURLY}, {_segments(24)}, q as (select seg, i, v, v / stddev_pop(v) over (partition by seg) as z from seg)"
    norms = "select seg, seg * {n} as start, round(max(case when i = 0 then x end), 4) as first, round(sqrt(sum(v * v)), 4) as norm from seg group by seg"
    return {
        "windows_hourly": f"{HOURLY}, {_windows(24)} select start, round(avg(x), 6) as mean, round(stddev_pop(x), 6) as sd, round(sum(x * x), 4) as energy from w group by start",
        "windows_by_type": """with pts as (select event_type as series_id, cast(row_number() over (partition by event_type order by event_id) - 1 as bigint) as pos, value as x from events),
            w as (select series_id, pos as start, avg(x) over f as m, stddev_pop(x) over f as sd, count(*) over f as n from pts window f as (partition by series_id order by pos rows between current row and 49 following))
            select series_id, start, round(m, 3) as mean, round(sd, 3) as sd from w where n = 50""",
        "segments_hourly": f"{HOURLY}, {_segments(48)} {norms.format(n=48)}",
        "segments_daily": f"{DAILY}, {_segments(14)} {norms.format(n=14)}",
        "blocks_equal_windows": f"{HOURLY}, {_windows(24)} select start, round(avg(x), 6) as mean from w group by start",
        "dist_emb_zm": EMB.format(n=20) + pair.format(c="v"),
        "dist_emb_zn": EMB.format(n=20) + pair.format(c="z"),
        "dist_sbd_emb": EMB.format(n=8)
        + """, size as (select vec_id, sqrt(sum(v * v)) as n from c group by 1),
            cross_ as (select a.vec_id as a, b.vec_id as b, a.i - b.i as shift, sum(a.v * b.v) as p from c a join c b on a.vec_id < b.vec_id group by 1, 2, 3)
            select x.a, x.b, round(1 - max(p) / any_value(s.n * t.n), 4) as dist from cross_ x join size s on s.vec_id = x.a join size t on t.vec_id = x.b group by 1, 2""",
        "dist_dtw_small": """with recursive e as (select vec_id, list_transform(embedding, lambda x: cast(x as double)) as xs from embeddings where vec_id < 8),
            m as (select vec_id, xs, list_avg(xs) as m from e), c as (select vec_id, list_transform(xs, lambda x: x - m) as xs from m),
            t as (select a.vec_id as a, b.vec_id as b, a.xs as x, b.xs as y, 0 as k, list_transform(range(65), lambda i: case when i = 0 then 0.0::double else 'infinity'::double end) as last_, list_transform(range(65), lambda i: 'infinity'::double) as before_ from c a join c b on a.vec_id < b.vec_id
              union all
              select a, b, x, y, k + 1, list_transform(range(65), lambda i: case when i between 1 and 64 and k + 1 - i between 1 and 64 then pow(x[i] - y[k + 1 - i], 2) + least(last_[i], last_[i + 1], before_[i]) else 'infinity'::double end), last_ from t where k < 128)
            select a, b, round(sqrt(last_[65]), 4) as dist from t where k = 128""",
        "dist_zm_pairs": f"{days} {day.format(c='v')}",
        "dist_zn_pairs": f"{days} {day.format(c='z')}",
        "dist_min_place": f"""{HOURLY}, day as (select cast(floor(pos / 24) as int) as seg, pos % 24 as i, x - avg(x) over (partition by floor(pos / 24)) as v from pts where pos < 24 * floor((select count(*) from pts) / 24)),
            two as (select cast(floor(pos / 48) as bigint) as p, pos % 48 as i, x from pts where pos < 48 * floor((select count(*) from pts) / 48)),
            piece as (select p, o, i - o as i, x - avg(x) over (partition by p, o) as v from two, (select unnest(range(25)) as o) where i between o and o + 23),
            d as (select day.seg, piece.p, piece.o, sqrt(sum((day.v - piece.v) ** 2)) as d from day join piece on piece.p = cast(floor(day.seg / 2) as bigint) - 1 and piece.i = day.i group by 1, 2, 3)
            select seg, p as pattern, round(min(d), 4) as dist from d group by 1, 2""",
    }


def _linkage() -> dict[str, str]:
    head = f"""{HOURLY}, {_segments(48)}, m as (select cast(floor(seg / 5) as bigint) as grp, seg, i, v from seg where seg < 5 * floor((select max(seg) + 1 from seg) / 5)),
        pairs as (select a.grp, a.seg as s, b.seg as t, sqrt(sum((a.v - b.v) ** 2)) as d from m a join m b on b.grp = a.grp + 1 and a.i = b.i group by 1, 2, 3),
        mean as (select grp, i, avg(v) as v from m group by 1, 2),
        gap as (select a.grp, sqrt(sum((a.v - b.v) ** 2)) as d from mean a join mean b on b.grp = a.grp + 1 and a.i = b.i group by 1)"""
    return {
        **{f"link_{k}": f"{head} select grp, round({f}(d), 4) as dist from pairs group by grp" for k, f in (("single", "min"), ("complete", "max"), ("average", "avg"))},
        "link_centroid": f"{head} select grp, round(d, 4) as dist from gap",
        "link_ward": f"{head} select grp, round(sqrt(2 * 5 * 5 / 10.0) * d, 4) as dist from gap",
        "adjacent_gap_links": f"{DAILY}, {_segments(14)} select a.seg, round(sqrt(sum((a.v - b.v) ** 2)), 2) as dist from seg a join seg b on b.seg = a.seg + 1 and a.i = b.i group by a.seg",
        "chain_cut_toy": f"""{DAILY}, {_segments(14)}, links as (select a.seg + 1 as right_, sqrt(sum((a.v - b.v) ** 2)) as d from seg a join seg b on b.seg = a.seg + 1 and a.i = b.i group by a.seg),
            o as (select right_, d, row_number() over (order by d) as rn from links),
            joins as (select rn, right_, d from o where rn <= (select count(*) from o) - 3),
            ends as (select j.rn, j.right_, j.d,
              coalesce((select max(k.right_) from o k where k.right_ < j.right_ and k.rn > j.rn), 0) as lo,
              coalesce((select min(k.right_) from o k where k.right_ > j.right_ and k.rn > j.rn), (select count(*) + 1 from o)) - 1 as hi from joins j)
            select cast(rn - 1 as int) as step, cast(lo as int) as lo, cast(hi as int) as hi, round(d, 2) as height from ends""",
        "cut_toy_rules": f"""{DAILY}, {_segments(14)}, links as (select a.seg + 1 as right_, sqrt(sum((a.v - b.v) ** 2)) as d from seg a join seg b on b.seg = a.seg + 1 and a.i = b.i group by a.seg),
            o as (select right_, d, row_number() over (order by d) as rn from links),
            ends as (select j.rn, j.d,
              coalesce((select max(k.right_) from o k where k.right_ < j.right_ and k.rn > j.rn), 0) as lo,
              coalesce((select min(k.right_) from o k where k.right_ > j.right_ and k.rn > j.rn), (select count(*) + 1 from o)) - 1 as hi from o j where j.rn <= (select count(*) from o) - 3),
            h as (select s.seg as seed, row_number() over (partition by s.seg order by e.rn) as p, e.d as h from (select distinct seg from seg) s join ends e on s.seg between e.lo and e.hi),
            j as (select seed, p, h, h - lag(h) over (partition by seed order by p) as j, sum(h) over (partition by seed order by p) as total from h),
            r as (select seed, p - 1 as step, j, avg(j) over w as m, stddev_pop(j) over w as sd, avg(j) over (partition by seed order by p) as so_far, total / p as level, p from j where j is not null window w as (partition by seed)),
            l as (select seed, step, j, unnest(['mean_jump', 'running_mean', 'mean_plus_std', 'printed']) as rule, unnest([m, so_far, m + sd, level - so_far / p]) as "limit" from r)
            select cast(seed as int) as seed, rule, cast(step as int) as step, round("limit", 2) as "limit", j > "limit" as cut from l""",
        "ca_rounds_daily": f"""{DAILY.replace('with', 'with recursive', 1)}, {_segments(14)},
            leaf as (select seg, list(v order by i) as t from seg group by seg),
            st as (select 0 as k, list({{'lo': seg, 'hi': seg, 'n': 1, 't': t}} order by seg) as c from leaf
              union all
              select k + 1, list_transform(list_filter(range(1, len(c) + 1), lambda i: not list_contains(tk, i - 1)), lambda i: case when list_contains(tk, i) then {{'lo': c[i].lo, 'hi': c[i + 1].hi, 'n': c[i].n + c[i + 1].n, 't': list_transform(range(1, 15), lambda j: c[i].t[j] + c[i + 1].t[j])}} else c[i] end)
              from (select *, list_transform(list_slice(list_sort(list_transform(list_filter(range(1, len(ds) + 1), lambda i: (i = 1 or ds[i] <= ds[i - 1]) and (i = len(ds) or ds[i] <= ds[i + 1])), lambda i: {{'d': ds[i], 'i': i}})), 1, len(c) - 20), lambda x: x.i) as tk
                from (select *, list_transform(range(1, len(c)), lambda i: sqrt(2.0 * c[i].n * c[i + 1].n / (c[i].n + c[i + 1].n) * list_sum(list_transform(range(1, 15), lambda j: pow(c[i].t[j] / c[i].n - c[i + 1].t[j] / c[i + 1].n, 2))))) as ds from st where len(c) > 20))),
            f as (select unnest(c) as c, unnest(range(len(c))) as id from st where k = (select max(k) from st))
            select cast(id as int) as cluster_id, cast(c.lo as int) as seg_lo, cast(c.hi as int) as seg_hi, cast(c.n as int) as n from f""",
        "ca_ward_norepair_daily": f"""{DAILY.replace('with', 'with recursive', 1)}, {_segments(14)},
            leaf as (select seg, list(v order by i) as t from seg group by seg),
            st as (select 0 as k, list({{'lo': seg, 'hi': seg, 'n': 1, 't': t}} order by seg) as c, 0.0::double as h, 0 as lo, 0 as hi, 0 as n from leaf
              union all
              select k + 1, list_concat(list_concat(list_slice(c, 1, place - 1), [{{'lo': c[place].lo, 'hi': c[place + 1].hi, 'n': c[place].n + c[place + 1].n, 't': list_transform(range(1, 15), lambda j: c[place].t[j] + c[place + 1].t[j])}}]), list_slice(c, place + 2, len(c))),
                ds[place], c[place].lo, c[place + 1].hi, c[place].n + c[place + 1].n
              from (select *, list_position(ds, list_min(ds)) as place from (select *, list_transform(range(1, len(c)), lambda i: sqrt(2.0 * c[i].n * c[i + 1].n / (c[i].n + c[i + 1].n) * list_sum(list_transform(range(1, 15), lambda j: pow(c[i].t[j] / c[i].n - c[i + 1].t[j] / c[i + 1].n, 2))))) as ds from st where len(c) > 1)))
            select cast((select count(*) from leaf) + k - 1 as int) as node, cast(lo as int) as lo_seg, cast(hi as int) as hi_seg, cast(n as int) as n, round(h, 2) as height, false as reverted from st where k > 0""",
    }


# -- the fixed model ---------------------------------------------------------------------------------

FIXED = f"""{HOURLY}, {_segments(48)},
    pat as (select cast(floor(seg / 5) as int) as pid, i, avg(v) as v from seg where seg < 15 group by 1, 2), {_windows(24)},
    wc as (select start, i, x - avg(x) over (partition by start) as v, x from w),
    off as (select unnest(range(25)) as o),
    piece as (select pid, o, i - o as i, v - avg(v) over (partition by pid, o) as v from pat, off where i between o and o + 23),
    prof as (select start, pid, min(d) as d from (select wc.start, p.pid, p.o, sqrt(sum((wc.v - p.v) ** 2)) as d from wc join piece p on p.i = wc.i group by 1, 2, 3) group by 1, 2),
    span as (select unnest([0, 1, 2]) as pid, unnest([0, 240, 480]) as first, unnest([239, 479, 719]) as last),
    tau as (select prof.pid, avg(d) as tau from prof join span on span.pid = prof.pid and start >= first and start + 23 <= last group by 1),
    mem as (select start, prof.pid, d, tau, case when d <= tau then 1.0 else exp(-10 / tau * (d - tau)) end as phi from prof join tau on tau.pid = prof.pid)"""


def _presence(spans: str, mode: str) -> str:
    meets = {"overlap": "c > 0", "majority": "2 * c >= sp", "contain": "c >= sp"}[mode]
    return f"""sw as (select pid, start, avg(phi) over f as m, count(*) over f as n from mem window f as (partition by pid order by start rows between current row and 23 following)),
        met as (select sw.pid, m, least(start + 46, last) - greatest(start, first) + 1 as c, least(last - first + 1, 47) as sp from sw join ({spans}) sn on sn.pid = sw.pid where n = 24),
        freq as (select pid, min(m) as freq from met where {meets} group by pid)"""


SPANS = "select pid, first, last from span"
UNEVEN = "select unnest([0, 1, 2]) as pid, unnest([0, 48, 480]) as first, unnest([47, 479, 719]) as last"


def _active(freq: str, ahead: int = 0) -> str:
    source = {"0.6": "select *, 0.6 as freq from mem", "own": "select mem.*, freq from mem join freq on freq.pid = mem.pid"}[freq]
    ahead_ = "current row" if not ahead else f"{ahead} following"
    return f"act as (select *, pa >= freq as on_ from (select *, avg(phi) over (partition by pid order by start rows between 24 preceding and {ahead_}) as pa from ({source})))"


ACT = f"{FIXED}, {_active('0.6')}"
NEAR = """best as (select start, arg_min(pid, d) filter (where on_) as q, min(d) filter (where on_) as dq, arg_min(pid, d) as qa, min(d) as da, bool_or(on_) as any_on from act group by start),
    near as (select start, coalesce(q, qa) as nearest, coalesce(dq, da) as d, not any_on as no_active from best)"""


def _score(frame: str) -> str:
    return f"""low as (select start, pid, min(d) over (partition by pid order by start rows between {frame}) as low from prof),
        sc as (select near.start, low.low as score, near.nearest, near.no_active from near join low on low.start = near.start and low.pid = near.nearest)"""


TRAIL = f"{ACT}, {NEAR}, {_score('24 preceding and current row')}"


def _fixed() -> dict[str, str]:
    owners = "select unnest([0, 0, 0, 1, 1, 2, 2, 2]) as pid, unnest([0, 2, 4, 6, 8, 10, 12, 14]) as seg"
    cand = """, cand as (select seg as cand, i, v, seg / 20.0 as freq from seg where seg % 5 = 0 and seg < 15),
        far as (select c.cand, p.pid, any_value(c.freq) as freq, sqrt(sum((c.v - p.v) ** 2)) as d from cand c join (select pid, i, v from pat) p on p.i = c.i group by 1, 2),
        test as (select cand, bool_and(d > 1400 + 100 * pid) as dissimilar, any_value(freq) > 0.1 as frequent from far group by cand)"""
    return {
        "centroids_fixed": f"{FIXED} select pid as pattern_id, cast(i as int) as i, round(v, 6) as v from pat",
        "tau_fixed": f"""{FIXED}, sd as (select floor(s.seg / 5) as pid, s.seg, sqrt(sum((s.v - p.v) ** 2)) as d from seg s join pat p on p.pid = floor(s.seg / 5) and p.i = s.i where s.seg < 15 group by 1, 2)
            select tau.pid as pattern_id, round((select avg(d) + 3 * stddev_pop(d) from sd where sd.pid = tau.pid), 4) as tau_segment, round(tau.tau, 4) as tau_sub from tau""",
        "win_fixed": "select cast(least(20 * 24, 2 * 5 * 48) as bigint) as win",
        "unclustered_fixed": f"{HOURLY}, {_segments(48)} select distinct 0 as cluster_id, seg from seg where seg < 1",
        "phi_hourly": f"{FIXED} select start, pid as pattern_id, round(d, 4) as d, round(phi, 4) as phi from mem",
        "phi_avg_hourly": f"{ACT} select start, pid as pattern_id, round(pa, 4) as phi_avg from act",
        "active_flags_hourly": f"{ACT} select start, pid as pattern_id, on_ as active from act",
        "active_flags_trained": f"{FIXED}, {_presence(SPANS, 'overlap')}, {_active('own')} select start, pid as pattern_id, on_ as active from act",
        "active_delta_hourly": f"{FIXED}, {_active('0.6', 12)} select start, pid as pattern_id, on_ as active from act",
        "drift_events_hourly": f"{ACT}, l as (select *, lag(on_) over (partition by pid order by start) as was from act) select start as pos, case when on_ then 'on_recurring' else 'off' end as kind, pid as pattern_id from l where was is not null and was <> on_",
        "score_nearest_active": f"{ACT}, {NEAR} select start, nearest, round(d, 4) as d, no_active from near",
        "score_no_active_fallback": f"{ACT}, {NEAR} select start, nearest, round(d, 4) as d from near where no_active",
        "score_trailing_min": f"{TRAIL} select start, round(score, 4) as score from sc",
        "score_centered": f"{ACT}, {NEAR}, {_score('12 preceding and 12 following')} select start, round(score, 4) as score from sc",
        "score_weighted_sum": f"{FIXED} select start, round(sum((pid + 1) / 6.0 * d), 4) as score from prof group by start",
        "score_offline_nearest_time": f"""{FIXED}, own as ({owners}), gaps as (select s.start, own.pid, own.seg, abs(own.seg * 48 + 24 - (s.start + 12)) as gap from (select distinct start from prof) s, own),
            pick as (select start, arg_min(pid, gap * 1000 + seg) as pid from gaps group by start)
            select pick.start, pick.pid as nearest, round(prof.d, 4) as score from pick join prof on prof.start = pick.start and prof.pid = pick.pid""",
        "static_model_score": f"""{FIXED}, wz as (select start, i, case when sd < 1e-9 then 0 else v / sd end as z from (select *, stddev_pop(v) over (partition by start) as sd from wc)),
            pz as (select pid, o, i, case when sd < 1e-9 then 0 else v / sd end as z from (select *, stddev_pop(v) over (partition by pid, o) as sd from piece)),
            zd as (select start, pid, min(d) as d from (select wz.start, pz.pid, pz.o, sqrt(sum((wz.z - pz.z) ** 2)) as d from wz join pz on pz.i = wz.i group by 1, 2, 3) group by 1, 2)
            select start, round(sum(d) / 3, 4) as score from zd group by start""",
        **{f"freq_{m}_fixed": f"{FIXED}, {_presence(UNEVEN, m)} select pid as pattern_id, round(freq, 4) as freq from freq" for m in ("overlap", "majority", "contain")},
        "label_threshold": f"{TRAIL} select start, cast(score > 1000 as int) as label from sc",
        "label_radius": f"{TRAIL} select start, cast(no_active or score > tau as int) as label from sc join tau on tau.pid = sc.nearest",
        "label_topk": f"{TRAIL} select start, cast(row_number() over (order by score desc, start) <= 20 as int) as label from sc",
        "label_quantile": f"{TRAIL} select start, cast(score > (select quantile_disc(score, 0.95) from sc) as int) as label from sc",
        "alarms_per_series": f"""{TRAIL.replace('with', 'with recursive', 1)}, o as (select start, score, row_number() over (order by score desc, start) as rn from sc),
            pickd as (select 1 as k, start, score, [start] as taken from o where rn = 1
              union all
              select k + 1, n.start, n.score, list_append(p.taken, n.start) from pickd p, lateral (select start, score from o where len(list_filter(p.taken, lambda t: abs(t - o.start) < 24)) = 0 order by rn limit 1) n where k < 5)
            select cast(k as int) as rank, start, round(score, 4) as score from pickd""",
        **{f"admit_{n}": f"{FIXED}{cand} select cand, {c} as {a} from test" for n, c, a in (("dissimilar", "dissimilar", "dissimilar"), ("frequent", "frequent", "frequent"), ("both", "dissimilar and frequent", "admitted"))},
        "fp_after_drift": f"""{TRAIL}, l as (select *, lag(on_) over (partition by pid order by start) as was from act), dr as (select distinct start as pos from l where was is not null and was <> on_)
            select count(distinct sc.start) as fp_after_drift from sc join dr on sc.start between dr.pos and dr.pos + 48 where score > 1000 having count(*) > 0""",
        "discord_left_hourly": f"""{HOURLY}, {_windows(24)}, z as (select start, i, case when sd < 1e-9 then 0 else v / sd end as z from (select start, i, x - avg(x) over (partition by start) as v, stddev_pop(x) over (partition by start) as sd from w)),
            l as (select start, list(z order by i) as z from z group by start),
            d as (select a.start, min(list_sum(list_transform(list_zip(a.z, b.z), lambda p: (p[1] - p[2]) ** 2))) as s from l a join l b on b.start <= a.start - 24 group by 1)
            select start, round(sqrt(s), 4) as score from d""",
        "profile_full_hourly": f"""{HOURLY}, {_windows(24)}, z as (select start, i, case when sd < 1e-9 then 0 else v / sd end as z from (select start, i, x - avg(x) over (partition by start) as v, stddev_pop(x) over (partition by start) as sd from w)),
            l as (select start, list(z order by i) as z from z group by start),
            d as (select a.start, min(list_sum(list_transform(list_zip(a.z, b.z), lambda p: (p[1] - p[2]) ** 2))) as s from l a join l b on abs(b.start - a.start) >= 24 group by 1)
            select start, round(sqrt(s), 4) as score from d""",
        "batch_ids": "select cast(floor(event_id / 5000) as bigint) as batch_id, count(*) as n, min(event_id) as first_pos from events group by 1",
    }


# -- carriers ----------------------------------------------------------------------------------------


def u(key: str, salt: str) -> str:
    return f"(cast('0x' || substr(md5(concat({key}, ':{salt}')), 1, 13) as bigint) / {float(1 << 52)!r})"


def normal(key: str, salt: str) -> str:
    return f"(sqrt(-2 * ln(greatest({u(key, salt + 'a')}, 1e-12))) * cos(2 * {math.pi!r} * {u(key, salt + 'b')}))"


def shape(concept: str, pos: str = "pos", names: str = "ABCD") -> str:
    cases = []
    for k, name in enumerate(names):
        wave = " + ".join(f"{w!r} * sin({h} * 2 * {math.pi!r} * ({pos} % 50) / 50)" for h, w in enumerate(CONCEPTS[name], 1) if w)
        cases.append(f"when {concept} = {k} then {wave}")
    return f"(case {' '.join(cases)} else 0.0 end)"


N = "(select count(*) from events)"


def carrier(concept: str = "0", inside: str = "false") -> str:
    return f"""with sp as (select event_id as pos, (value - 50) / 50 as noise from events), cc as (select *, cast({concept} as int) as concept, {inside} as in_transition from sp),
        b as (select *, {shape('concept')} + 0.05 * noise as x, 'carrier/' || cast(cast(floor(pos / 50) as bigint) as varchar) as wk, cast(floor(pos / 50) as bigint) as wid from cc)"""


def shown(x: str = "x", hit: str = "false", extra: str = "", source: str = "b") -> str:
    return f"{extra} select pos, round(case when {hit} then {x} else x end, 6) + 0.0 as x, concept, in_transition, cast({hit} as int) as y_true from {source}"


SCALE_HIT, SCALE_X = f"{u('wk', 'hit1')} < 0.05", f"x * (1.5 + 1.5 * {u('wk', 'factor1')})"


def gradual(cuts: list[str], width: str, seed: int) -> tuple[str, str]:
    draw = u("pos", f"gradual{seed}")
    piece = " + ".join(f"(case when abs(pos - {p}) <= {width} / 2 then cast({draw} < 1 / (1 + exp(-4.0 * (pos - {p}) / {width})) as int) else cast(pos >= {p} as int) end)" for p in cuts)
    return f"({piece}) % 4", " or ".join(f"abs(pos - {p}) <= {width} / 2" for p in cuts)


def _injectors() -> dict[str, str]:
    cuts = [f"floor({N} / 4)", f"floor({N} / 2)"]
    concept, inside = gradual(cuts, f"({N} * 0.05)", 1)
    laws = {
        "uniform": "q",
        "gauss": f"0.5 + 0.18 * {normal('id', 'place1')}",
        "rayleigh": "0.3 * sqrt(-2 * ln(q))",
        "invrayleigh": "0.3 / sqrt(-2 * ln(q))",
    }
    place = {}
    for law, at in laws.items():
        chosen = f""", draws as (select id, greatest({u('id', 'place1')}, 1e-9) as q from (select unnest(range(6 * floor({N} / 50)::bigint)) as id)),
            ww as (select id, cast(floor(({at}) * floor({N} / 50)) as bigint) as w from draws), ok as (select w, min(id) as id from ww where w >= 0 and w < floor({N} / 50) group by w),
            ch as (select w from ok order by id limit (select cast(round_even(0.1 * floor({N} / 50), 0) as bigint))), bb as (select b.*, ch.w is not null as chosen from b left join ch on ch.w = b.wid)"""
        place[f"inj_place_{law}"] = carrier() + shown(SCALE_X, "chosen", chosen, "bb")
    like = f"{shape('0')} * (1.0 + 0.1 * {normal('wk', 'like1')}) + 0.05 * noise"
    return {
        "inj_scale": carrier() + shown(SCALE_X, SCALE_HIT),
        "inj_scaled_normal": carrier() + shown(f"x * (2.0 + 0.1 * {normal('wk', 'factor1')})", f"{u('wk', 'hit1')} < 0.1"),
        "inj_lookalike": carrier(f"case when pos < {N} * 1 / 10.0 then 0 else 1 end") + shown(like, f"(concept = 1 and {u('wk', 'hit1')} < 0.1)"),
        "inj_abrupt": carrier(f"cast(pos >= {cuts[0]} as int) + cast(pos >= {cuts[1]} as int)") + shown(),
        "inj_gradual": carrier(concept, inside) + shown(),
        "inj_recurring": carrier("cast(floor(pos / 500) as bigint) % 3") + shown(),
        "inj_ratio": carrier(f"case when pos < {N} * 8 / 10.0 then 0 else 1 end") + shown(),
        "inj_alternate": carrier("case when pos % 1500 < 500 then 0 else 1 end") + shown(),
        **place,
    }


SPIKES = f"{carrier()}, t as (select {SCALE_HIT} as hit, x, {SCALE_X} as y from b), sp2 as (select round(abs(case when hit then y else x end), 3) as score, cast(hit as int) as y from t)"


def _auc(source: str, score: str = "score", y: str = "y") -> str:
    return f"""select sum(cast({y} > 0 as bigint)) as n_pos, sum(cast({y} <= 0 as bigint)) as n_neg,
        (sum(case when {y} > 0 then r end) - sum(cast({y} > 0 as bigint)) * (sum(cast({y} > 0 as bigint)) + 1) / 2.0) / sum(cast({y} > 0 as bigint)) / sum(cast({y} <= 0 as bigint)) as a
        from (select *, rank() over (order by {score}) + (count(*) over (partition by {score}) - 1) / 2.0 as r from {source})"""


def _measures() -> dict[str, str]:
    labels = "(select n_chars as score, {y} as y from documents join labels using (doc_id))"
    doc = lambda y: f"select cast(n_pos as bigint) as n_pos, cast(n_neg as bigint) as n_neg, round(a, 6) as auc from ({_auc(labels.format(y=y))})"
    names = ["A", "B", "C", "D"]
    heat = f"""{carrier('cast(floor(pos / 500) as bigint) % 4')}, t as (select pos, concept, {SCALE_HIT} as hit, case when {SCALE_HIT} then {SCALE_X} else x end as x from b),
        it as (select substr('ABCD', concept + 1, 1) || case when hit then '*' else '' end as name, pos % 50 as i, avg(x) as v from t group by 1, 2),
        c as (select name, i, v - avg(v) over (partition by name) as v from it), m as (select a.name as a, b.name as b, round(sqrt(sum((a.v - b.v) ** 2)), 4) as d from c a join c b on a.i = b.i group by 1, 2)"""
    region_concept, region_inside = f"(case when abs(pos - floor({N} / 2)) <= {N} * 0.1 / 2 then cast({u('pos', 'gradual1')} < 1 / (1 + exp(-4.0 * (pos - floor({N} / 2)) / ({N} * 0.1))) as int) else cast(pos >= floor({N} / 2) as int) end) % 2", f"abs(pos - floor({N} / 2)) <= {N} * 0.1 / 2"
    return {
        "auc_doc_toxic": doc("toxic"),
        "auc_doc_quality": doc("1 - quality"),
        "auc_carrier": f"{SPIKES} select cast(n_pos as bigint) as n_pos, cast(n_neg as bigint) as n_neg, round(a, 4) as auc from ({_auc('sp2')})",
        "auc_binned": f"""{SPIKES}, bn as (select floor(score / 0.05) as score, y from sp2), c as (select score, sum(y) as p, sum(1 - y) as n from bn group by 1)
            select cast(n_pos as bigint) as n_pos, cast(n_neg as bigint) as n_neg, round(a, 4) as auc, round((select sum(p * n) from c) / (2.0 * n_pos * n_neg), 4) as bound from ({_auc('bn')})""",
        "roc_points": f"""{SPIKES}, bn as (select cast(floor(score / 0.1) as bigint) as t, y from sp2)
            select t as threshold, round((select count(*) from bn where y = 0 and bn.t >= d.t) / cast((select count(*) from bn where y = 0) as double), 4) as fpr,
              round((select count(*) from bn where y = 1 and bn.t >= d.t) / cast((select count(*) from bn where y = 1) as double), 4) as tpr from (select distinct t from bn) d""",
        "confusion": f"""{SPIKES}, k as (select count(*) filter (score > 1.5 and y = 1) as tp, count(*) filter (score > 1.5 and y = 0) as fp, count(*) filter (score <= 1.5 and y = 1) as fn, count(*) filter (score <= 1.5 and y = 0) as tn from sp2)
            select tp, fp, fn, tn, round(tp / nullif(tp + fp, 0)::double, 4) as precision, round(tp / nullif(tp + fn, 0)::double, 4) as recall, round(fp / nullif(fp + tn, 0)::double, 4) as fpr, round(2.0 * tp / nullif(2 * tp + fp + fn, 0)::double, 4) as f1 from k""",
        "dissim_matrix": f"{heat} select * from m",
        "op_cross_pivot": f"{heat} select a as item, max(d) filter (b = 'A') as \"A\", max(d) filter (b = 'B') as \"B\", max(d) filter (b = 'C') as \"C\", max(d) filter (b = 'D') as \"D\" from m group by a",
        "anom_dissim": f"""{carrier()}, f as (select unnest([0.5, 1.0, 2.0, 3.0])::double as factor),
            hit as (select factor, wid, pos % 50 as i, x * (factor + 0.1 * {normal('wk', 'factor1')}) as x from b, f where {u('wk', 'hit1')} < 0.1 and wid < floor({N} / 50)),
            w as (select factor, wid, i, x - avg(x) over (partition by factor, wid) as v from hit),
            pt as (select p, i, {shape('p', 'i')} as x from (select unnest(range(4)) as p), (select unnest(range(50)) as i)), pc as (select p, i, x - avg(x) over (partition by p) as v from pt),
            d as (select factor, wid, p, sqrt(sum((w.v - pc.v) ** 2)) as d from w join pc using (i) group by 1, 2, 3), near as (select factor, wid, min(d) as d from d group by 1, 2),
            between_ as (select avg(d) as m, max(d) as x from (select sqrt(sum((a.v - b.v) ** 2)) as d from pc a join pc b on a.i = b.i and a.p < b.p group by a.p, b.p))
            select factor, count(*) as n, round(avg(d), 4) as mean, round(stddev_pop(d), 4) as sd, round(any_value(m), 4) as normal_mean, round(any_value(between_.x), 4) as normal_max from near, between_ group by factor""",
        "unclustered_by_rmin": f"""{DAILY}, {_segments(14)}, k as (select distinct seg, cast(floor(sqrt(seg)) as int) as c from seg), sz as (select c, count(*) as n from k group by c),
            r as (select unnest([0.001, 0.01, 0.05, 0.1])::double as r_min) select r_min, cast(sum(n) as bigint) as unclustered from r, sz where n < greatest(2, ceil(r_min * (select count(*) from k))) group by r_min""",
        "by_region": f"""{carrier(region_concept, region_inside)}, t as (select case when {SCALE_HIT} then 'anomaly' when in_transition then 'drift' else 'normal' end as region, abs(case when {SCALE_HIT} then {SCALE_X} else x end) as s from b)
            select region, count(*) as n, round(avg(s), 4) as mean_score from t group by rollup (region)""",
        "dataset_card": f"""{carrier('cast(floor(pos / 500) as bigint) % 4')}, t as (select {SCALE_HIT} as hit, case when {SCALE_HIT} then {SCALE_X} else x end as x from b)
            select 'carrier' as series_id, count(*) as n_points, cast(sum(cast(hit as int)) as bigint) as n_anomalous, round(avg(x), 4) as mean_x, round(stddev_pop(x), 4) as sd_x from t""",
        "stability": """with e as (select event_type, value, cast(minute(ts) >= 45 as int) as y, rank() over (partition by event_type order by value) + (count(*) over (partition by event_type, value) - 1) / 2.0 as r from events),
            a as (select event_type, (sum(case when y = 1 then r end) - sum(y) * (sum(y) + 1) / 2.0) / sum(y) / sum(1 - y) as v from e group by 1)
            select 'value' as method, round(stddev_pop(v), 4) as spread, round(max(v) - min(v), 4) as range, round(avg(v), 4) as mean from a""",
    }


# -- operators around --------------------------------------------------------------------------------


def _around() -> dict[str, str]:
    marks = f"""with {_grid('orders', 'o_orderdate', 'o_totalprice', 'day')}, marks as (select pos, coalesce(x, 0) as mark from raw where pos % 10 = 3),
        g2 as (select unnest(generate_series((select min(l_shipdate) from lineitem), (select max(l_shipdate) from lineitem), interval 1 day)) as ts), days as (select cast(row_number() over (order by ts) - 1 as bigint) as pos from g2)"""
    half = "select user_id, event_type from events where value > {}"
    dow = "(select *, dayofweek(ts) + 1 as dow from events)"
    length = "(select role, conv_id, turn, length(text) as n from conversations)"
    return {
        "op_asof_backward": f"{marks} select d.pos, round(m.mark, 2) as mark from days d asof left join marks m on d.pos >= m.pos",
        "op_asof_forward": f"{marks} select d.pos, round(m.mark, 2) as mark from days d asof left join marks m on d.pos <= m.pos",
        "op_asof_nearest": f"""{marks}, b as (select d.pos, m.pos as mp, m.mark from days d asof left join marks m on d.pos >= m.pos), a as (select d.pos, m.pos as mp, m.mark from days d asof left join marks m on d.pos <= m.pos)
            select a.pos, round(case when b.mp is null then a.mark when a.mp is null or a.pos - b.mp <= a.mp - a.pos then b.mark else a.mark end, 2) as mark from a join b on a.pos = b.pos""",
        "op_range_join": """with b as (select o_orderkey, date_diff('day', date '1970-01-01', cast(o_orderdate as date)) as b_lo, date_diff('day', date '1970-01-01', cast(o_orderdate as date)) + 9 as b_hi from orders)
            select w * 7 as a_lo, w * 7 + 6 as a_hi, b.* from b, unnest(range(b_lo // 7, b_hi // 7 + 1)) t(w)""",
        "op_semi": "select doc_id, n_chars from documents where doc_id in (select doc_id from labels where toxic = 1)",
        "op_anti": "select doc_id, n_chars from documents where doc_id not in (select doc_id from labels)",
        "op_unpivot": """with t as (select event_type as series_id, round(avg(value), 4) as mean, round(max(value), 4) as high from events group by 1)
            select series_id, 'mean' as metric, mean as value from t union all select series_id, 'high', high from t""",
        "op_agg_stats": "select event_type as series_id, count(*) as n, round(sum(value), 3) as total, round(avg(value), 3) as mean, round(min(value), 3) as low, round(max(value), 3) as high, round(stddev_pop(value), 3) as sd, round(var_pop(value), 3) as variance, round(avg(z ** 3), 3) as skew, round(avg(z ** 4) - 3, 3) as kurt from (select *, (value - avg(value) over (partition by event_type)) / stddev_pop(value) over (partition by event_type) as z from events) group by 1",
        "op_grouping_sets": "select day, event_type, count(*) as n, round(sum(value), 2) as v from (select *, cast(dayofmonth(ts) as int) as day from events) group by grouping sets ((event_type), (day), ())",
        "op_cube": f"select event_type, cast(dow as int) as dow, count(*) as n from {dow} group by cube (event_type, dow)",
        "op_rollup": f"select event_type, cast(dow as int) as dow, count(*) as n from {dow} group by rollup (event_type, dow)",
        "op_rank_suite": """select doc_id, row_number() over w as row_number, rank() over w as rank, dense_rank() over w as dense_rank, round(percent_rank() over w, 4) as percent_rank, round(cume_dist() over w, 4) as cume_dist, ntile(4) over w as ntile
            from documents window w as (partition by lang order by n_chars, doc_id)""",
        "op_range_frame": f"{DAILY} select pos, round(avg(x) over (order by pos range between 6 preceding and current row), 2) as v from pts",
        "op_rolling": f"{DAILY} select pos, round(max(x) over (order by pos rows between 3 preceding and 3 following), 2) as v from pts",
        "op_running": f"{DAILY} select pos, round(cast(sum(floor(x)) over (order by pos) as double), 1) as v from pts",
        "op_islands": f"""{DAILY}, f as (select pos, x > 300000 as high from pts), c as (select *, coalesce(cast(lag(high) over (order by pos) <> high as int), 0) as ch from f), i as (select *, sum(ch) over (order by pos) as island from c)
            select cast(island as bigint) as island, any_value(high) as high, min(pos) as first_pos, max(pos) as last_pos, count(*) as n from i group by island""",
        "op_topk": "select doc_id, n_chars from documents order by n_chars desc, doc_id limit 10",
        "op_topk_per": "select doc_id, lang, n_chars, rank from (select doc_id, lang, n_chars, cast(row_number() over (partition by lang order by n_chars desc, doc_id) as int) as rank from documents) where rank <= 3",
        "op_percentile": "select event_type as series_id, round(quantile_cont(value, 0.9), 4) as q from events group by 1",
        "op_count_distinct": "select event_type, count(distinct user_id) as n from events group by 1",
        "op_json_props": "select cast(json_extract(props, '$.k') as int) as k, count(*) as n from events group by 1",
        "op_tumbling": "select cast(floor(epoch(ts) / 21600) * 21600 as bigint) as start_s, count(*) as n, round(sum(value), 2) as v from events group by 1",
        "op_sliding": "select cast(floor(epoch(ts) / 7200) * 7200 - k * 7200 as bigint) as start_s, count(*) as n, max(value) as v from events, (select unnest([0, 1, 2]) as k) group by 1",
        "op_session": """with l as (select event_type, ts, coalesce(cast(ts - lag(ts) over (partition by event_type order by ts) >= interval 30 minute as int), 1) as new from events),
            i as (select *, sum(new) over (partition by event_type order by ts) as k from l) select event_type, cast(floor(epoch(min(ts))) as bigint) as start_s, count(*) as n from i group by event_type, k""",
        "op_lateral_topk": f"select role, conv_id, turn, n from (select *, row_number() over (partition by role order by n desc, conv_id, turn) as rn from {length}) where rn <= 2",
        "op_full_outer": "select user_id, a, b from (select user_id, count(*) as a from events where value > 100 group by 1) full outer join (select user_id, count(*) as b from events where value < 2 group by 1) using (user_id)",
        "op_sample_md5": f"select event_id from events where {u('event_id', 'sample')} < 0.1",
        "op_union": f"{half.format(150)} union all {half.format(200)}",
        "op_intersect": f"{half.format(100)} intersect {half.format(120)}",
        "op_except": f"{half.format(50)} except {half.format(120)}",
        "op_except_all": f"{half.format(50)} except all {half.format(120)}",
        "stream_hourly": """with h as (select cast(epoch(date_trunc('hour', ts)) as bigint) as start_s, sum(value) as x, count(*) as n from events group by 1)
            select start_s, round(x, 2) as x, n from h where start_s + 3600 <= (select epoch(max(ts)) - 3600 from events)""",
        "stream_session": """with l as (select event_type, ts, coalesce(cast(ts - lag(ts) over (partition by event_type order by ts) >= interval 30 minute as int), 1) as new from events),
            i as (select *, sum(new) over (partition by event_type order by ts) as k from l), s as (select event_type, min(ts) as a, max(ts) as b, count(*) as n from i group by event_type, k)
            select event_type, cast(floor(epoch(a)) as bigint) as start_s, n from s where b + interval 30 minute <= (select max(ts) - interval 1 hour from events)""",
        "stream_detect_equals_batch": "select cast(range as bigint) as start, true as same from range((select count(*) - 49 - 100 from events))",
        "stream_late_count": f"""with e as (select event_type, ts, cast(floor(event_id * 4 / (select count(*) from events)) as int) + cast({u('event_id', 'late')} < 0.1 as int) as a from events),
            m as (select event_type, a, max(ts) as top from e group by 1, 2), b as (select event_type, a, max(top) over (partition by event_type order by a rows between unbounded preceding and 1 preceding) as top from m)
            select event_type, count(*) as n, cast(sum(case when ts < b.top - interval 1 hour then 1 else 0 end) as bigint) as late from e join b using (event_type, a) group by 1""",
        "stream_dedup": "select event_id, value from events",
    }


def all_sql() -> dict[str, str]:
    return _sources() | _distances() | _linkage() | _fixed() | _injectors() | _measures() | _around()
