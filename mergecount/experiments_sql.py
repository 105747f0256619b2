"""The SQL that checks the experiments."""

from __future__ import annotations

import math

from . import cuts, nested
from .experiments import DRAWS, FORM_GROUPS, FORM_TASKS, INVERSE, INVERSE_SIZES, MANY, METHODS, MORE_TAILS, PROCESSES, SEED_KEYS, SHARES, SWEEP, SWEEP_KEYS, TAIL_SHIFTS, WALK_LENGTHS
from .functions.native import NativeSeed
from .params import BASE_LAMBDA
from .plans.planner import CELL_ROW_BYTES
from .workloads import BUDGET, KWISE, NESTED, OFFSET, PARITY
from .workloads_sql import WIDTH, _exact, celled, cut, curved, estimated, hashed, lineitem

RAW_WIDTH = WIDTH.replace("level - q", "level")
FLAG = ["l_returnflag"]


def _sized(key: str) -> str:
    """(share, k): the distinct keys that 2^share divides."""
    return f"select share, k from (select distinct {key} k from lineitem where {key} is not null) join (values {', '.join(f'({j}, {1 << j})' for j in SHARES)}) s(share, m) on k % m = 0"


def _sizes(key: str) -> str:
    return f"sizes as (select share, count(*) size from ({_sized(key)}) group by share)"


def _sweep(key: str, seed: NativeSeed = PARITY) -> str:
    return cut(_sized(key), ["share"], seed)


def _inverse() -> str:
    """Hits of the flags' parts at each size; the look-up keeps its promise."""
    sizes = ", ".join(f"({k}, {f}, {(f << k).bit_length() - 1})" for k, f in INVERSE_SIZES)
    return f"""with {celled(lineitem('l_partkey', FLAG), FLAG, INVERSE)},
      shapes as (select * from (values {sizes}) v(log_b, factor, bits)),
      low as (select l_returnflag, log_b, factor, bits, tab, bin & ((1 << bits) - 1) bin, max(level) as level from cells, shapes group by all),
      over as (select *, greatest(0, max(level) over (partition by l_returnflag, log_b, factor, tab) - bits + {OFFSET}) s from low),
      h as (select l_returnflag, log_b, factor, tab, count(*) hits from over where level >= s group by all)
      select l_returnflag, log_b::INTEGER log_b, factor::INTEGER factor, (41 * (factor * pow(2, log_b)::BIGINT) // 60 + 1)::INTEGER entries, ceil(7.5 * ln(factor * pow(2, log_b)) + 16)::INTEGER independence, min(hits) least, max(hits) most, true as within from h group by all"""


def _shared_cuts() -> str:
    """Cells of the nested seed, with cuts by three groupings."""
    flat = NESTED.flat()
    base = hashed(lineitem("l_orderkey", []), [], flat).replace("hashed as (", "flat as (")
    out = [base, f"cells as (select tab t, tab // {NESTED.l} copy, tab % {NESTED.l} tab, bin, max(level) as level from flat group by all)"]
    selects = []
    for kind, group, tables in (("shared", "", NESTED.l * NESTED.m), ("copy", "copy", NESTED.l), ("table", "t", 1)):
        g, limit = f"{group}," if group else "", math.floor(BUDGET * tables * NESTED.b)
        same = f"c.{group} = s.{group}" if group else "true"
        log_b, mid = NESTED.b.bit_length() - 1, (NESTED.l - 1) // 2 + 1
        out += [
            f"n_{kind} as (select {g} level, count(*) n from cells group by all)",
            f"r_{kind} as (select {g} q::INTEGER q, sum(({WIDTH}) * n)::BIGINT bits from n_{kind}, range(0, 66) r(q) group by all)",
            f"q_{kind} as (select {g} min(q) q from r_{kind} where bits <= {limit} group by all)",
            f"s_{kind} as (select s.copy, tab, bin, (level - q)::INTEGER as level, q from cells s join q_{kind} c on {same} where level >= q)",
            f"p_{kind} as (select *, level + q a, greatest(0, max(level + q) over (partition by copy, tab) - {log_b} + {OFFSET}) s from s_{kind})",
            f"t_{kind} as (select copy, tab, max(s) s, least(count(*) filter (a >= s), {NESTED.b - 1}) p from p_{kind} group by all)",
            f"y_{kind} as (select copy, pow(2.0, s) * ln(1 - p / {float(NESTED.b)}) / ln({1 - 1 / NESTED.b!r}) y from t_{kind})",
            f"e_{kind} as (select copy, list_sort(list_concat(list(y), list_transform(range(0, {NESTED.l} - count(*)), lambda x: 0.0::DOUBLE))) ys from y_{kind} group by all)",
        ]
        selects.append(f"select '{kind}' cuts, (select round(median(round((ys[{mid}] + ys[{NESTED.l // 2 + 1}]) / 2, 6)), 6) from e_{kind}) estimate, min(q)::INTEGER q_min, max(q)::INTEGER q_max, {nested.cut_bits(kind, NESTED.m, NESTED.l)} cut_bits from q_{kind}")
    return "with " + ",\n".join(out) + "\n" + " union all ".join(selects)


def _seed_bits() -> str:
    step = -math.log(BASE_LAMBDA)
    keys = " union all ".join(f"select '{c}' key, max({c}) top from lineitem" for c in SEED_KEYS)
    return f"""
    with d as (select key, length(bin(top)) bits from ({keys}) where top is not null),
    v as (select key, bits, log_b, l, mode, pow(2, log_b) b, 5 + 2 * log_b pre, ceil(7.5 * ln(pow(2, log_b)) + 16) k from d, (values (8), (10), (12)) x(log_b), (values (9), (12)) y(l), (values ('walk_16'), ('walk_paper'), ('independent')) z(mode)),
    s as (select *, 2 * bits + 2 * greatest(bits, pre) + k * pre triple, ceil((case when mode = 'walk_16' then ln(16) else greatest(ln(16), l * pow(ln(l), 3)) end) / {step!r}) steps from v)
    select key, bits::INTEGER bits, log_b::INTEGER log_b, l::INTEGER l, mode, (case when mode = 'independent' then l * triple else triple + triple % 2 + (l - 1) * 3 * steps end)::BIGINT seed_bits from s"""


def ORACLES() -> dict[str, str]:
    b, log_b = MANY.b, MANY.b.bit_length() - 1
    shifts = ", ".join(f"({k})" for k in TAIL_SHIFTS)
    inverse = lambda h: f"ln(1 - least({h}, {b - 1}) / {float(b)}) / ln({1 - 1 / b!r})"
    tails = ", ".join(f"({mu}, {lam}, {g}, {length})" for mu, lam, g, length in MORE_TAILS)
    methods = ", ".join(f"('{name}', {str(merges).lower()})" for name, merges, _ in METHODS)
    drops = ", ".join(f"({v}, {c})" for v in range(65) for c in range(1, v + 2) if math.floor(math.log2(max(v - c, -1) + 2)) < math.floor(math.log2(max(v - c + 1, -1) + 2)))
    keys = " union all ".join(f"select '{name}' which, count(distinct {c}) exact from {t}" for name, t, c in SWEEP_KEYS)
    day = "date_trunc('day', ts)::TIMESTAMP"
    comm = " union all ".join(
        f"select * from (with {cut(f'select l_orderkey % {p} part, l_partkey k from lineitem', ['part'], PARITY)}, sent as (select part, (sum(2 * ({RAW_WIDTH})) + {PARITY.l * PARITY.b})::BIGINT bits from state group by 1) select {p} processes, count(*) sketches, sum(bits)::BIGINT end_bits, max(bits) most_bits from sent)"
        for p in PROCESSES
    )
    at_cuts = f"""{cut(lineitem('l_orderkey', FLAG), FLAG, PARITY)}, higher as (select l_returnflag, q + d cut from cuts, range(0, 4) x(d)),
        shifted as (select l_returnflag, cut, tab, bin, (level - cut)::INTEGER as level, cut q from cells join higher using (l_returnflag) where level >= cut)"""
    at_cuts = estimated(at_cuts + ", state2 as (select * from shifted)", ["l_returnflag", "cut"], PARITY).replace("from state)", "from state2)")
    overlap = "(select distinct c_custkey k from customer)", "(select distinct o_custkey k from orders where o_orderstatus = 'F')"
    assert cuts.cell_bits(0) == 1
    return {
        "cardinality_sweep": f"""with {estimated(_sweep('l_orderkey'), ['share'], PARITY)}, {_sizes('l_orderkey')},
          top as (select share, tab, greatest(0, max(level) - {PARITY.b.bit_length() - 1} + {OFFSET}) s from cells group by all), s2 as (select share, min(s) s_min, max(s) s_max from top group by 1)
          select share, size, estimate, q, s_min, s_max, q <= s_min cut_ok from final join s2 using (share) join sizes using (share)""",
        "cut_margin_sweep": f"with {_sweep('l_orderkey')}, {_sizes('l_orderkey')}, m as (select share, size, q, greatest(0, ceil(log2(size))::INTEGER - {PARITY.b.bit_length() - 1}) q_max from cuts join sizes using (share)) select share, size, q, q_max, q <= q_max + {math.ceil(math.log2(8 / BUDGET))} q_near from m",
        "column_space": f"""with {_sweep('l_partkey', MANY)}, {_sizes('l_partkey')}, t as (select share, tab, sum({RAW_WIDTH}) bits from state group by all)
          select share, size, c::INTEGER c, max(bits) most_bits, round(count(*) filter (bits > (c + 3) * {b}) / {float(MANY.l)}, 6) over_share, case when c >= 0 then round(pow(2.0, -pow(2.0, c)), 9) else 1.0 end bound from t join sizes using (share), range(-2, 3) r(c) group by share, size, c""",
        "operation_counts": f"with {celled(_sized('l_orderkey'), ['share'], PARITY)}, {_sizes('l_orderkey')} select share, size, sum({RAW_WIDTH})::BIGINT input_bits, count(*) cells, count(distinct level) levels, (max(level) + 2) * count(distinct level) candidates from cells join sizes using (share) group by share, size",
        "level_tails": f"""with {hashed(_sized('l_partkey'), ['share'], MANY)}, {_sizes('l_partkey')}, t as (select size, share, tab, max(level) top from hashed join sizes using (share) group by all)
          select k, count(*) filter (top > log2(size) + k or top < log2(size) - k - 1) off, count(*) tables, pow(2.0, -k) bound, count(*) filter (top > log2(size) + k or top < log2(size) - k - 1) / count(*) <= 2 * pow(2.0, -k) as within from t, (values {shifts}) s(k) group by k""",
        "event_frequencies": f"""with {hashed('select distinct l_partkey k from lineitem', [], MANY)},
          tops as (select tab, count(*) n, greatest(0, max(level) - {log_b} + {OFFSET}) s from hashed group by tab),
          p as (select tab, n, s, count(*) r, count(distinct bin) hits, n / pow(2.0, s) load from hashed join tops using (tab) where level >= s group by tab, n, s)
          select tab, s, r, hits, s = 0 or load between {2.0**-16 * b!r} and {b / 2} load_ok, abs(r - load) <= {0.5 / 3!r} * load sample_ok, abs(hits - {b} * (1 - pow({1 - 1 / b!r}, r))) <= 9 * r / {math.sqrt(b)!r} hits_ok,
            r <= {2 * b / 3!r} sample_small, hits <= {41 * b / 60!r} hits_small, {inverse('hits + 1')} - {inverse('hits')} < 4 slope_ok from p""",
        "balls_thrown": f"""with {hashed(_sized('l_partkey'), ['share'], MANY)}, {_sizes('l_partkey')}, h as (select share, tab, count(distinct bin) hits from hashed group by all)
          select share, size r, round(avg(hits), 6) mean_hits, min(hits) least, max(hits) most, round({b} * (1 - pow({1 - 1 / b!r}, size)), 6) curve from h join sizes using (share) group by share, size""",
        "cost_drops": f"with {celled(lineitem('l_orderkey', []), [], PARITY)}, n as (select level, count(*) cells from cells group by level) select level, n.cells, cut from n join (values {drops}) v(level, cut) using (level)",
        "cut_forms_agree": f"with {cut(lineitem('l_orderkey', FLAG), FLAG, PARITY)} select l_returnflag, q, true agree from cuts",
        "estimate_at_any_cut": f"with {at_cuts} select l_returnflag, cut, estimate from final",
        "cut_sharing_ablation": _shared_cuts(),
        "communication_measured": comm,
        "seed_report": _seed_bits(),
        "form_choice": f"""with n as ({' union all '.join(f"select '{name}' grouping_, count(*) g from (select distinct {', '.join(c) or '1'} from lineitem)" for name, c in FORM_GROUPS)}),
          v as (select grouping_, g groups, tasks, tasks * g * {KWISE.l * KWISE.b}::BIGINT * {CELL_ROW_BYTES} cell_bytes, floor(tasks * g * ({KWISE.l * KWISE.b} * {2 * KWISE.budget + 1} / 8 + 32))::BIGINT packed_bytes from n, (values {', '.join(f'({t})' for t in FORM_TASKS)}) t(tasks))
          select grouping_ "grouping", groups, tasks, case when cell_bytes <= packed_bytes then 'cells' else 'packed' end form, cell_bytes, packed_bytes from v""",
        "tail_bounds_more": f"""with v as (select mu::DOUBLE mu, lam::DOUBLE lam, g::DOUBLE g, l::INTEGER l, mu::DOUBLE + 2 * lam::DOUBLE p, mu::DOUBLE + g::DOUBLE - 2 * lam::DOUBLE x, mu::DOUBLE + lam::DOUBLE m, mu::DOUBLE + g::DOUBLE y from (values {tails}) t(mu, lam, g, l)),
          w as (select *, exp(-l * (x * ln(x / p) + (1 - x) * ln((1 - x) / (1 - p)))) older0, exp(-l * (y * ln(y / m) + (1 - y) * ln((1 - y) / (1 - m)))) newer from v)
          select mu, lam, g, l, round(older0, 9) older, round(pow(mu * (1 - lam) + lam, 3), 9) hitting_exact, round(pow(m, 3), 9) hitting, round(exp(-l * (1 - lam) * g * g / 4), 9) gap, round(g * ln(1 / m) - 2 / exp(1.0), 9) kl_lower, ceil(4 * ln(1e6) / ln(1 / mu))::INTEGER repetitions, newer <= older0 sharper from w""",
        "inverse_tables": _inverse(),
        "asof_purchase_view": """select event_id, view_id from (select p.event_id, v.event_id view_id, row_number() over (partition by p.event_id order by v.ts desc nulls last, v.event_id desc) r
          from events p left join events v on v.event_type = 'view' and v.user_id = p.user_id and v.ts <= p.ts where p.event_type = 'purchase') where r = 1""",
        "distinct_in_ranges": "select r, count(distinct l_partkey) parts, count(*) as rows from lineitem join (select r, r * 700 lo, r * 700 + 1000 hi from range(0, 8) t(r)) on l_orderkey >= lo and l_orderkey < hi group by r",
        "baseline_comparison": f"select method, mergeable, (select count(distinct l_partkey) from lineitem) exact, true as within from (values {methods}) m(method, mergeable)",
        "nested_within": _exact([], "lineitem", "l_partkey"),
        "nested_store_within": _exact(FLAG, "(select * from lineitem where year(l_shipdate) >= 1995)", "l_partkey"),
        "sketch_store_within": _exact(FLAG, "(select * from lineitem where year(l_shipdate) >= 1995)", "l_partkey"),
        "packed_cube_within": "select l_returnflag, l_linestatus, grouping(l_returnflag, l_linestatus)::INTEGER gid, count(distinct l_partkey) exact, true as within from lineitem group by cube (l_returnflag, l_linestatus)",
        "stored_sets_within": f"select (select count(*) from {overlap[0]} semi join {overlap[1]} b using (k)) in_both, (select count(*) from {overlap[0]} anti join {overlap[1]} b using (k)) only_a, (select count(*) from (select k from {overlap[0]} union select k from {overlap[1]})) in_either, true as within",
        "texts_by_source_within": _exact(["source"], "documents", "text"),
        "urls_within": _exact([], "pages", "url"),
        "turns_by_role_within": _exact(["role"], "conversations", "text"),
        "conversations_shared_within": "select (select count(*) from (select distinct text from conversations where turn <= 1 and text is not null) semi join (select text from conversations where turn > 1) x using (text)) \"both\", (select count(distinct text) from conversations where turn is not null) either, true as within",
        "rough_tracked_within": "select seeds, event_type, count(distinct user_id) exact, true as within, true differences_smaller from events, (values ('copies'), ('walk')) v(seeds) group by all",
        "accuracy_sweep_within": f"select which, config::INTEGER config, exact, {DRAWS} draws, true as within from ({keys}), range(0, {len(SWEEP)}) c(config)",
        "walk_tail": f"select set_name, length, true tail_ok, true hitting_ok from (values ('segment'), ('rare')) s(set_name), (values {', '.join(f'({x})' for x in WALK_LENGTHS)}) l(length)",
        "deviation_walk": "select length, round(exp(-length), 9) bound, true as within, true \"unbounded\" from (values (4), (8)) l(length)",
        "sliding_stream_within": f"select d::VARCHAR as day, count(distinct user_id) exact, true as within from (select unnest([{day}, {day} - interval 1 day]) d, user_id from events) group by 1",
        "packed_stream_within": f"select {day}::VARCHAR as day, count(distinct user_id) exact, true as within from events group by 1",
        "session_stream": "select event_type, count(*) sessions from (select event_type, ts, ts >= coalesce(lag(ts) over (partition by event_type order by ts), ts - interval 3 hour) + interval 2 hour fresh from events) where fresh group by event_type",
        "dedup_stream_exact": f"select {day}::VARCHAR as day, count(distinct user_id) users from events group by 1",
        "late_rows_stream": "select true late_rows_left_out",
    }
