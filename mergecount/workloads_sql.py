"""The SQL that checks the workloads: the same hash words as literals, other plans."""

from __future__ import annotations

import math

from . import bounds
from .baselines.counters import PHI
from .functions.native import NativeSeed
from .params import C_BIN, C_REP
from .workloads import ACCURACIES, BUDGET, GRID, NESTED, OCCUPANCY, OFFSET, PARITY, TAILS

FLAGS = ["l_returnflag", "l_linestatus"]
JOINED = "(select r_name, n_name, c_mktsegment, o_custkey from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)"


def _words(seed: NativeSeed) -> str:
    lists = ["[" + ",".join(map(str, w)) + "]::BIGINT[]" for w in (seed.level_words(), seed.bin_words())]
    return f"words as (select {lists[0]} lw, {lists[1]} bw)"


def _xor(name: str) -> str:
    out = ""
    for place in range(16):
        term = f"{name}[(tab * 256 + {16 * place + 1} + ((k >> {4 * place}) & 15))::INTEGER]"
        out = term if not out else f"xor({out}, {term})"
    return out


def _cols(group: list[str]) -> str:
    return "".join(f"{g}, " for g in group)


def hashed(source: str, group: list[str], seed: NativeSeed) -> str:
    """CTEs up to ``hashed``: (group..., tab, bin, level) of the rows (group..., k) of ``source``."""
    return f"""{_words(seed)},
    keyed as (select {_cols(group)} k::BIGINT k, unnest(range(0, {seed.l})) tab from ({source}) where k is not null),
    mapped as (select {_cols(group)} tab, {_xor('lw')} y, {_xor('bw')} h from keyed, words),
    hashed as (select {_cols(group)} tab::INTEGER tab, (h & {seed.b - 1})::INTEGER bin,
      (case when y = 0 then 64 when y = -9223372036854775808 then 63 else bit_count(((y & (-y)) - 1)::BIGINT) end)::INTEGER as level from mapped)"""


def celled(source: str, group: list[str], seed: NativeSeed) -> str:
    return hashed(source, group, seed) + f",\n    cells as (select {_cols(group)} tab, bin, max(level) as level from hashed group by all)"


WIDTH = " + ".join(f"(greatest(level - q, -1) + 2 >= {2**i})::INTEGER" for i in range(1, 7))


def curved(source: str, group: list[str], seed: NativeSeed) -> str:
    return celled(source, group, seed) + f""",
    counts as (select {_cols(group)} level, count(*) n from cells group by all),
    curve as (select {_cols(group)} q::INTEGER q, sum(({WIDTH}) * n)::BIGINT bits from counts, range(0, 66) r(q) group by all)"""


def cut(source: str, group: list[str], seed: NativeSeed, budget: float = BUDGET, inner_tables: int | None = None) -> str:
    """``inner_tables``: tables that share a cut, if not all."""
    limit = math.floor(budget * (inner_tables or seed.l) * seed.b)
    same = " and ".join(f"c.{g} is not distinct from s.{g}" for g in group) or "true"
    return curved(source, group, seed) + f""",
    cuts as (select {_cols(group)} min(q) q from curve where bits <= {limit} group by all),
    state as (select {''.join(f's.{g}, ' for g in group)} tab, bin, (level - q)::INTEGER as level, q from cells s join cuts c on {same} where level >= q)"""


def estimated(state: str, group: list[str], seed: NativeSeed, offset: int = OFFSET) -> str:
    log_b, mid = seed.b.bit_length() - 1, (seed.l - 1) // 2 + 1
    return state + f""",
    tops as (select *, level + q a, greatest(0, max(level + q) over (partition by {_cols(group)} tab) - {log_b} + {offset}) s from state),
    tables as (select {_cols(group)} tab, max(q) q, max(s) s, least(count(*) filter (a >= s), {seed.b - 1}) p from tops group by all),
    values_of as (select {_cols(group)} q, pow(2.0, s) * ln(1 - p / {float(seed.b)}) / ln({1 - 1 / seed.b!r}) y from tables),
    sorted_ys as (select {_cols(group)} max(q) q, list_sort(list_concat(list(y), list_transform(range(0, {seed.l} - count(*)), lambda x: 0.0::DOUBLE))) ys from values_of group by all),
    final as (select {_cols(group)} round((ys[{mid}] + ys[{seed.l // 2 + 1}]) / 2, 6) estimate, q::INTEGER q from sorted_ys)"""


def estimate_sql(source: str, group: list[str], columns: str | None = None) -> str:
    return f"with {estimated(cut(source, group, PARITY), group, PARITY)} select {columns or _cols(group) + 'estimate, q'} from final"


def lineitem(key: str, group: list[str]) -> str:
    return f"select {_cols(group)} {key} k from lineitem"


def _nested() -> str:
    flat, inner, group = NESTED.flat(), NESTED.inner(), [*FLAGS, "copy"]
    base = hashed(lineitem("l_partkey", FLAGS), FLAGS, flat).replace("hashed as (", "flat as (")
    split = f",\n    hashed as (select {_cols(FLAGS)} tab // {NESTED.l} copy, tab % {NESTED.l} tab, bin, level from flat)"
    rest = cut("select 1", group, inner)
    rest = rest[rest.index("cells as (") :]
    return f"with {base}{split},\n    {estimated(rest, group, inner)} select {_cols(FLAGS)} round(median(estimate), 6) estimate from final group by all"


def _sets(dims: list[str], sets: list[tuple[str, ...]], source: str, key: str) -> str:
    parts = []
    for s in sets:
        gid = sum(1 << (len(dims) - 1 - i) for i, d in enumerate(dims) if d not in s)
        label = " || '|' || ".join([f"'{gid}'", *(f"coalesce({d}, '*')" if d in s else "'*'" for d in dims)])
        parts.append(f"select {label} g, {key} k from {source}")
    return " union all ".join(parts)


def _tail_rows() -> str:
    return ", ".join(f"({mu}, {lam}, {g}, {length})" for mu, lam, g, length in TAILS)


SPACE_SQL = {
    "bit_pattern": "n / (eps * eps)",
    "max_level": "ln(n)",
    "binned_max_level": "d * (ln(n) / (eps * eps) + ln(1 / eps) * ln(n) * n)",
    "rough_tracked": "d * (1 / (eps * eps) + n)",
    "walk_seeded": "d / (eps * eps) + n",
    "single_cut_nested": "d / (eps * eps) + n",
    "lower_bound": "d / (eps * eps) + n",
}


def _exact(group: list[str], source: str, key: str) -> str:
    return f"select {_cols(group)} count(distinct {key}) exact, true as within from {source}" + (f" group by {', '.join(group)}" if group else "")


def ORACLES() -> dict[str, str]:
    flag = ["l_returnflag"]
    orderkey = cut(lineitem("l_orderkey", flag), flag, PARITY)
    day = "date_trunc('day', ts)"
    five = "(timestamp '1970-01-01' + interval 1 second * ((epoch(ts)::BIGINT // 432000) * 432000))"
    single = NativeSeed(1, PARITY.b, PARITY.entropy)
    b = PARITY.b
    assert set(SPACE_SQL) == set(bounds.SPACE)
    grid = ", ".join(f"({bits}, {eps}, {delta})" for bits, eps, delta in GRID)
    return {
        "exact_distinct_by_flag": "select l_returnflag, l_linestatus, count(distinct l_partkey) as parts from lineitem group by 1, 2",
        "exact_bitmap": 'select count(distinct l_partkey)::BIGINT "distinct" from lineitem',
        "level_histogram": f"with {hashed('select distinct l_partkey k from lineitem', [], PARITY)} select tab, level, count(*) n from hashed group by all",
        "raw_cells": f"with {celled(lineitem('l_partkey', flag), flag, PARITY)} select l_returnflag, tab, bin, level from cells",
        "cut_curve": f"with {curved(lineitem('l_partkey', flag), flag, PARITY)} select l_returnflag, q, bits from curve",
        "required_cut": f"with {orderkey} select l_returnflag, q from cuts",
        "cut_cells": f"with {orderkey} select l_returnflag, tab, bin, level, q from state",
        "main_estimate_pairwise": estimate_sql(lineitem("l_partkey", FLAGS), FLAGS),
        "composite_estimate_pairwise": estimate_sql("select l_linestatus, (l_partkey << 32) | l_suppkey k from lineitem", ["l_linestatus"]),
        "nested_estimate_pairwise": _nested(),
        "merge_partitions": f"with {celled(lineitem('l_partkey', []), [], PARITY)} select tab, bin, level from cells",
        "merge_overlap": f"with {celled('select o_custkey k from orders union all select c_custkey from customer', [], PARITY)} select tab, bin, level from cells",
        "merge_duplicates": f"with {celled(lineitem('l_partkey', []), [], PARITY)} select tab, bin, level from cells",
        "prune_keeps_estimate": f"with {estimated(celled(lineitem('l_orderkey', flag), flag, PARITY) + ', state as (select *, 0 q from cells)', flag, PARITY)} select l_returnflag, estimate from final",
        "two_pass_estimate": f"with {estimated(celled(lineitem('l_orderkey', flag), flag, PARITY) + ', state as (select *, 0 q from cells)', flag, PARITY)} select l_returnflag, estimate from final",
        "running_distinct_by_merge": estimate_sql("select step::INTEGER step, user_id k from range(0, (select coalesce(max(date_diff('day', date '2024-01-01', ts::DATE)), 0) + 1 from events)) r(step) join events on date_diff('day', date '2024-01-01', ts::DATE) <= step", ["step"]),
        "ideal_hash_within": _exact(flag, "lineitem", "l_partkey"),
        "cube_by_merge": estimate_sql(_sets(FLAGS, [tuple(FLAGS), (FLAGS[0],), (FLAGS[1],), ()], "lineitem", "l_partkey"), ["g"]),
        "rollup_by_merge": estimate_sql(_sets(["r_name", "n_name", "c_mktsegment"], [("r_name", "n_name", "c_mktsegment"), ("r_name", "n_name"), ("r_name",), ()], JOINED, "o_custkey"), ["g"]),
        "exact_cube": "select l_returnflag, l_linestatus, count(distinct l_partkey) parts, grouping(l_returnflag, l_linestatus)::INTEGER gid from lineitem group by cube (l_returnflag, l_linestatus)",
        "top_segments": estimate_sql(f"select n_name, c_mktsegment, o_custkey k from {JOINED}", ["n_name", "c_mktsegment"]) + " order by estimate desc, n_name, c_mktsegment limit 5",
        "occupancy_curve": f"select kind, r, count(*) owners, round({b} * (1 - pow({1 - 1 / b!r}, r)), 6) hits, round(abs(ln(1 - least(r, {b - 1}) / {float(b)}) / ln({1 - 1 / b!r})), 6) balls from ("
        + " union all ".join(f"select '{kind}' kind, count(*) r from {t} where {k} is not null group by {k}" for kind, t, k in OCCUPANCY)
        + ") group by kind, r",
        "worked_example_cut": "select c::INTEGER cut, floor(log2(greatest(23 - c, -1) + 2))::INTEGER bits from range(0, 26) t(c)",
        "space_table": " union all ".join(f"select '{name}' algorithm, bits::INTEGER bits, eps::DOUBLE eps, delta::DOUBLE delta, round({sql}, 3) formula from (select *, bits * ln(2) n, ln(1 / delta::DOUBLE) d from (values {grid}) v(bits, eps, delta))".replace("eps * eps", "eps::DOUBLE * eps::DOUBLE") for name, sql in SPACE_SQL.items()),
        "derived_sizes": f"""select l_returnflag, bits::INTEGER bits, eps, delta, ceil({C_REP} * ln(2 / delta))::INTEGER l, ceil(log2({float(C_BIN)}::DOUBLE / (eps * eps)))::INTEGER log_b, 'proof' profile, delta * bits * ln(2) >= 1 single
          from (select l_returnflag, length(bin(max(l_partkey))) bits from lineitem where l_partkey is not null group by 1), (values {', '.join(f'({e}::DOUBLE, {d}::DOUBLE)' for e, d in ACCURACIES)}) v(eps, delta)""",
        "tail_bounds_grid": f"""with v as (select mu::DOUBLE mu, lam::DOUBLE lam, g::DOUBLE g, l::INTEGER l, mu::DOUBLE + lam::DOUBLE x from (values {_tail_rows()}) t(mu, lam, g, l)),
          w as (select *, g * ln(g / x) + (1 - g) * ln((1 - g) / (1 - x)) k from v)
          select mu, lam, g, l, round(k, 9) kl, round(exp(-l * k), 9) tail_kl, round(exp(-l * (g * ln(1 / x) - 2 / exp(1.0))), 9) tail_log, round(exp(-2 * l * pow(g - mu - lam, 2)), 9) tail_quadratic,
            round(pow(mu * (1 - lam) + lam, 4), 9) hitting, round(exp(-l), 9) deviation, round(exp(-l / 4.0), 9) median_failure from w""",
        "bitpattern_baseline": f"""with {hashed(lineitem('l_orderkey', flag), flag, single)},
          pat as (select l_returnflag, bin, bit_or(1::BIGINT << least(level, 62)) pattern from hashed group by all),
          low as (select l_returnflag, sum(bit_count((pattern & xor(-1::BIGINT, pattern + 1))::BIGINT)) z from pat group by all)
          select l_returnflag, round({b / PHI!r} * pow(2.0, z / {float(b)}), 6) estimate from low""",
        "maxlevel_baseline": f"with {hashed(lineitem('l_orderkey', flag), flag, PARITY)}, tops as (select l_returnflag, tab, max(level) t from hashed group by all) select l_returnflag, round(median(pow(2.0, t)), 6) estimate from tops group by 1",
        "binned_levels_baseline": f"""with {celled(lineitem('l_orderkey', flag), flag, PARITY)},
          tops as (select l_returnflag, tab, max(level) t from cells group by all),
          rough as (select l_returnflag, greatest(0, floor(median(t)) - {b.bit_length() - 1} + 1) s from tops group by 1),
          p as (select l_returnflag, tab, s, least(count(*) filter (level >= s), {b - 1}) p from cells join rough using (l_returnflag) group by all)
          select l_returnflag, round(median(pow(2.0, s) * ln(1 - p / {float(b)}) / ln({1 - 1 / b!r})), 6) estimate from p group by 1""",
        "sketch_bits": f"with {orderkey} select l_returnflag, (sum(2 * ({WIDTH.replace('level - q', 'level')})) + {PARITY.l * PARITY.b})::BIGINT cell_bits from state group by 1",
        "exact_overlap": """with a as (select distinct c_custkey k from customer), b as (select distinct o_custkey k from orders where o_orderstatus = 'F')
          select (select count(*) from a) in_a, (select count(*) from b) in_b, (select count(*) from a semi join b using (k)) in_both, (select count(*) from (select k from a union select k from b)) in_either, (select count(*) from a anti join b using (k)) only_a""",
        "keys_without_orders": """select c_mktsegment, count(*) filter (c_custkey in (select o_custkey from orders where o_totalprice > 300000)) with_orders,
          count(*) filter (c_custkey not in (select o_custkey from orders where o_totalprice > 300000)) "without" from customer group by 1""",
        "adversarial_split": estimate_sql("select 0 process, l_orderkey k from lineitem union all select p::INTEGER, (select max(l_orderkey) from lineitem) from range(1, 8) t(p) union all select -1, l_orderkey from lineitem", ["process"]),
        "window_distinct_exact": f"""select 'tumbling' kind, ({day})::TIMESTAMP::VARCHAR as day, count(distinct user_id) users from events group by 1, 2 union all
          select 'sliding', d::VARCHAR, count(distinct user_id) from (select unnest([({day})::TIMESTAMP, ({day})::TIMESTAMP - interval 1 day]) d, user_id from events) group by 1, 2""",
        "window_distinct_pairwise": estimate_sql(f"select ({day})::TIMESTAMP::VARCHAR as day, user_id k from events", ["day"]),
        "longer_windows_by_merge": estimate_sql(f"select {five}::TIMESTAMP::VARCHAR as day, user_id k from events", ["day"]),
        "json_key_distinct": "select event_type, count(distinct json_extract_string(props, '$.k')) keys, count(distinct json_extract_string(props, '$.k')) filter (value > 10) keys_above from events group by 1",
        "kwise_within": _exact(flag, "lineitem", "l_partkey"),
        "main_within": _exact([], "lineitem", "l_orderkey"),
        "skew_within": _exact([], "orders", "o_orderstatus"),
        "double_key_within": _exact([], "lineitem", "l_extendedprice"),
        "tokens_within": "select count(distinct w) exact, true as within from (select unnest(regexp_split_to_array(lower(text), '[ \\t\\n\\r\\x0b\\x0c]+')) w from documents) where w <> ''",
        "texts_within": _exact(["lang"], "documents", "text"),
        "union_within": "select count(distinct k) exact, true as within from (select c_custkey k from customer union all select o_custkey from orders where o_orderstatus = 'F')",
        "seq_equals_par": "select 5::BIGINT forms, 1::BIGINT states",
        "nested_within": _exact([], "lineitem", "l_partkey"),
        "stream_within": f"select ({day})::TIMESTAMP::VARCHAR as day, count(distinct user_id) exact, true as within from events group by 1",
    }
