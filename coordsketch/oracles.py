"""SQL that computes the registered queries' rows from the raw tables, written apart from the Spark code."""

from __future__ import annotations

from .functions.solve import unit_nodes

SEED, K, K_SMALL, DRAWS, ERROR_K = 7, 64, 8, 8, 50


def _skew(key: str) -> str:
    return f"(100.0 / (1 + ({key} % 100)))::double"


def _u(seed: str, key: str) -> str:
    return f"((('0x' || substr(md5({seed} || ':' || ({key})::varchar), 1, 13))::bigint)::double + 0.5) / 4503599627370496.0"


_RANK = {"exponential": "-ln(u) / weight", "priority": "u / weight", "uniform": "u + 0.0"}


def _p(family: str, bound: str = "bound") -> str:
    body = {"exponential": f"(1.0 - exp(-weight * {bound}))", "priority": f"least(1.0, weight * {bound})", "uniform": f"least(1.0, {bound})"}[family]
    return f"(case when isinf({bound}) then 1.0 else {body} end)"


def _periods(weighted: bool) -> str:
    w = _skew("o_custkey") if weighted else "1.0::double"
    return f"""select distinct 'p' || p::varchar as set_id, o_custkey as key, {w} as weight, c_mktsegment as segment
      from (select o_custkey, floor(date_diff('day', date '1995-01-01', o_orderdate::date) / 90)::bigint as p from orders) o
      join customer on c_custkey = o_custkey where p between 0 and 4"""


def _buyers(brand: str | None = "Brand#6", weight: str = _skew("o_custkey")) -> str:
    chosen = f" where p_brand = '{brand}'" if brand else ""
    return f"""select distinct 'b' || l_partkey::varchar as set_id, o_custkey as key, {weight} as weight
      from lineitem join part on l_partkey = p_partkey join orders on l_orderkey = o_orderkey{chosen}"""


_BRANDS = """select p_brand as set_id, l_orderkey as key, 1.0::double as weight, max(n) as lines
      from lineitem join part on l_partkey = p_partkey join (select l_orderkey as o, count(*) as n from lineitem group by 1) on o = l_orderkey group by 1, 2"""


def _sketch(members: str, k: int, family: str, seed: str = f"'{SEED}'", key: str = "key", name: str = "sk") -> str:
    """CTEs m, r, pz and the sketch by name."""
    return f"""m as ({members}), r as (select *, {_RANK[family]} as rank from (select *, {_u(seed, key)} as u from m)),
      pz as (select *, row_number() over (partition by set_id order by rank, key) as pos from r),
      {name} as (select z.*, coalesce(b.rank, 'infinity'::double) as bound from pz z left join (select set_id as s, rank from pz where pos = {k} + 1) b on s = set_id where pos <= {k})"""


_FIRST = "qs as (select q.query_id::bigint as query_id, 'p' || i::varchar as set_id from (values (2), (3), (4), (5)) q(query_id), range(5) t(i) where i < q.query_id)"
_PAIRS = "pairs as (select * from (values (0::bigint, 'p0', 'p1'), (1::bigint, 'p1', 'p2'), (2::bigint, 'p2', 'p4'), (3::bigint, 'p3', 'p4')) t(query_id, a, b))"
_PAIR_SETS = "qs as (select query_id, a as set_id from pairs union all select query_id, b from pairs)"
_AT = "av as (select qs.query_id, sk.* from sk join qs using (set_id))"


def _comb(kind: str, k: int = K, attrs: str = ", any_value(segment) as segment") -> str:
    """CTE comb over av."""
    if kind == "short":
        return f"comb as (select query_id, key, any_value(weight) as weight, min(rank) as rank, any_value(low) as bound, list(distinct set_id) as mem, count(distinct set_id) as sets{attrs} from (select *, min(bound) over (partition by query_id) as low from av) where rank < low group by 1, 2)"
    if kind == "long":
        return f"comb as (select query_id, key, any_value(weight) as weight, min(rank) as rank, max(bound) as bound, list(distinct set_id) as mem, count(distinct set_id) as sets{attrs} from av group by 1, 2)"
    return f"""un as (select query_id, key, any_value(weight) as weight, min(rank) as rank, list(distinct set_id) as mem, count(distinct set_id) as sets{attrs} from av group by 1, 2),
      up as (select *, row_number() over (partition by query_id order by rank, key) as pos from un),
      ub as (select query_id, least(coalesce(min(case when pos = {k} + 1 then rank end), 'infinity'::double), (select min(bound) from av where av.query_id = up.query_id)) as bound from up group by query_id),
      comb as (select up.* exclude (pos), ub.bound from up join ub using (query_id) where pos <= {k} and rank < ub.bound)"""


def _base(kind: str, family: str = "exponential", weighted: bool = True) -> str:
    return f"with {_sketch(_periods(weighted), K, family)}, {_FIRST}, {_AT}, {_comb(kind)}"


def _pair_base(family: str = "exponential", weighted: bool = True, kind: str = "short") -> str:
    return f"with {_sketch(_periods(weighted), K, family)}, {_PAIRS}, {_PAIR_SETS}, {_AT}, {_comb(kind)}"


def _adj(family: str = "exponential") -> str:
    return f"weight / {_p(family)}"


_FIN = "case when isinf(bound) then null else round(bound, 8) end as bound"
_B = "segment = 'BUILDING'"


def _pair_sql(columns: str) -> str:
    adj = _adj()
    return f"""{_pair_base()}, lc as (select query_id, key, any_value(weight) as weight, max(bound) as bound from av group by 1, 2),
      l as (select query_id, sum({adj}) as u from lc group by 1),
      s as (select c.query_id, sum({adj}) as us, sum(case when sets = 2 then {adj} else 0 end) as i, sum(case when sets = 1 and mem[1] = a then {adj} else 0 end) as d from comb c join pairs using (query_id) group by 1)
      select query_id, {columns} from l join s using (query_id)"""


def _estimates(queries: list[tuple[int, str, str, int]]) -> str:
    """(query_id, condition, combination, number of first periods)."""
    parts = []
    for q, condition, kind, n in queries:
        taken = f"sum(case when {condition} then adj else 0 end)"
        error = f"sqrt(sum(case when {condition} then adj * adj * (1 - p) else 0 end))"
        parts.append(f"select {q}::bigint as query_id, round({taken}, 6) as estimate, count(*) filter (where {condition}) as n_sampled, round({error}, 6) as std_error, '{kind}' as combo from a_{kind} where query_id = {n}")
    kinds = sorted({k for _, _, k, _ in queries})
    ctes = ", ".join(f"a_{k} as (with {_comb(k)} select *, {_p('exponential')} as p, {_adj()} as adj from comb)" for k in kinds)
    return f"with {_sketch(_periods(True), K, 'exponential')}, {_FIRST}, {_AT}, {ctes} {' union all '.join(parts)}"


def _exact(condition: str) -> str:
    return f"with m as ({_periods(True)}), h as (select key, any_value(weight) as weight, list(distinct set_id) as mem, count(distinct set_id) as sets, any_value(segment) as segment from m group by 1) select 1::bigint as query_id, round(sum(case when {condition} then weight else 0 end), 6) as exact from h"


def _recip(shifts: str, x: str) -> str:
    return f"coalesce(list_sum([1.0 / (({x}) - s) for s in {shifts}]), 0.0)"


def _bisect(base: str, key: str, f: str, result: str) -> str:
    """base: CTE text making `base` with key, lo, hi and what f needs; f over x; result over root."""
    return f"""with recursive {base}, it as (select {key}, 0 as i, lo::double as lo, hi::double as hi from base
      union all select {key}, i + 1, case when f > 0 then x else lo end, case when f > 0 then hi else x end from
      (select it.{key}, it.i, it.lo, it.hi, (it.lo + it.hi) / 2 as x, ({f.replace('X', '((it.lo + it.hi) / 2)')}) as f from it join base using ({key}) where it.i < 60)),
      solved as (select {key}, (lo + hi) / 2 as root from it where i = 60)
      select {key}, {result} from base join solved using ({key})"""


def _shifted(source: str, by: str, condition: str) -> str:
    """CTE base0: by, bound, n, total, shifts, top and the same for the others (o)."""
    return f"""sh as (select *, coalesce(sum(weight) over (partition by {by}, c order by rank, key rows between unbounded preceding and 1 preceding), 0.0) as s from (select *, ({condition}) as c from {source})),
      base0 as (select {by}, any_value(bound) as bound, count(*) filter (where c) as n, coalesce(sum(weight) filter (where c), 0.0) as total, coalesce(list(s) filter (where c), []) as shifts, coalesce(max(s) filter (where c), 0.0) as top,
        count(*) filter (where not c) as on_, coalesce(sum(weight) filter (where not c), 0.0) as ototal, coalesce(list(s) filter (where not c), []) as oshifts, coalesce(max(s) filter (where not c), 0.0) as otop from sh group by {by})"""


_TOTALS = "tot as (select set_id, sum(weight) as w from m group by 1)"
_KNOWN = ("base as (select *, top as lo, w - otop as hi from base1)", f"{_recip('base.shifts', 'X')} - {_recip('base.oshifts', 'base.w - X')}", "case when n = 0 then 0.0 when on_ = 0 then w when isinf(bound) then total else least(greatest(root, total), w - ototal) end")


def _draws(members: str, family: str, k: int, draws: int, name: str = "sk") -> str:
    """CTEs t0 (distinct memberships) and sketches of every draw d, in name."""
    inner = f"select d || '|' || set_id as set_id, key, weight, d from (select distinct set_id, key, weight from ({members})), range(1, {draws + 1}) t(d)"
    return f"t0 as (select distinct set_id, key, weight from ({members})), {_sketch(inner, k, family, 'd::varchar', name=name)}"


_TRUTH = """h as (select key, any_value(weight) as weight, count(distinct set_id) as sets from t0 group by 1),
      tr0 as (select sum(weight) as u, sum(case when sets = (select count(distinct set_id) from t0) then weight else 0 end) as i, sum(case when sets = 1 then weight else 0 end) as h from h),
      tr as (select 'union' as measure, u as exact from tr0 union all select 'intersection', i from tr0 union all select 'jaccard', i / u from tr0 union all select 'hamming', h from tr0)"""


def _errors(members: str, family: str, k: int = ERROR_K, draws: int = DRAWS, pair: bool = False, where: str = "true") -> str:
    """members: set_id, key, weight. pair: two sets, with the distance and inclusion-exclusion as well."""
    pieces = []
    for kind in ("union", "short", "long"):
        cols = "sum(adj) as u, sum(case when sets = (select count(distinct set_id) from t0) then adj else 0 end) as i, count(*) as size"
        pieces.append(f"e_{kind} as (with {_comb(kind, k, '')} select query_id, {cols} from (select *, {_adj(family)} as adj from comb) group by 1)")
    rows = " union all ".join(
        f"select query_id, 'union' as measure, u as estimate, '{k}' as estimator, size from e_{k}" + ("" if k == "long" else f" union all select query_id, 'intersection', i, '{k}', size from e_{k} union all select query_id, 'jaccard', i / u, '{k}', size from e_{k}")
        for k in ("union", "short", "long")
    )
    if pair:
        rows += " union all " + " union all ".join(f"select query_id, 'hamming', u - i, '{e}', size from e_{e}" for e in ("union", "short"))
        rows += " union all select query_id, 'hamming', l.u - s.i, 'mixed', l.size from e_long l join e_short s using (query_id) union all select query_id, 'intersection', (select sum(weight) from t0) - u, 'inclusion_exclusion', size from e_long"
    return f"""with {_draws(members, family, k, draws)},
      av as (select d::bigint as query_id, sk.* from sk), {", ".join(pieces)}, est as ({rows}), {_TRUTH},
      err as (select measure, estimator, avg(abs(estimate - exact) / exact) as e, avg(size) as l from est join tr using (measure) where exact > 0 group by 1, 2)
      select a.measure, a.estimator, round(a.e, 6) as avg_rel_error, round(case when a.e = 0 then null else b.e / a.e end, 6) as improvement, round(a.l, 6) as mean_size, round(sqrt(a.l / {k}), 6) as predicted_gain, round(sqrt(2 / pi() / a.l), 6) as predicted_error
      from err a join err b on a.measure = b.measure and b.estimator = 'union' where {where}"""


def _union_errors(members: str, family: str, k: int, draws: int) -> str:
    """Only the union's rows; written without lists, for many sets."""
    low = "(select query_id, min(bound) as low from av group by 1)"
    return f"""with {_draws(members, family, k, draws)}, av as (select d::bigint as query_id, sk.* from sk), lows as {low},
      pl as (select query_id, key, any_value(weight) as weight, max(bound) as bound from av group by 1, 2),
      ps as (select av.query_id, key, any_value(weight) as weight, any_value(low) as bound from av join lows using (query_id) where rank < low group by 1, 2),
      u0 as (select query_id, key, any_value(weight) as weight, min(rank) as rank from av group by 1, 2), u1 as (select *, row_number() over (partition by query_id order by rank, key) as pos from u0),
      ub as (select query_id, least(coalesce(min(case when pos = {k} + 1 then rank end), 'infinity'::double), any_value(low)) as bound from u1 join lows using (query_id) group by 1),
      pu as (select u1.query_id, key, weight, ub.bound from u1 join ub using (query_id) where pos <= {k} and rank < ub.bound),
      est as (""" + " union all ".join(f"select query_id, '{n}' as estimator, sum({_adj(family)}) as estimate, count(*) as size from p{n[0]} group by 1" for n in ("union", "short", "long")) + f"""),
      tr as (select sum(weight) as exact from (select key, any_value(weight) as weight from t0 group by 1)),
      err as (select estimator, avg(abs(estimate - exact) / exact) as e, avg(size) as l from est, tr group by 1)
      select 'union' as measure, a.estimator, round(a.e, 6) as avg_rel_error, round(case when a.e = 0 then null else b.e / a.e end, 6) as improvement, round(a.l, 6) as mean_size, round(sqrt(a.l / {k}), 6) as predicted_gain, round(sqrt(2 / pi() / a.l), 6) as predicted_error from err a join err b on b.estimator = 'union'"""


def _by(name: str, cases: dict[str, str]) -> str:
    return " union all ".join(f"select {value} as {name}, * from ({sql})" for value, sql in cases.items())


def _ipps(k: int) -> str:
    """CTE n: set_id, thr of the distinct memberships t0."""
    return f"""w as (select *, row_number() over (partition by set_id order by weight desc, key) - 1 as j, coalesce(sum(weight) over (partition by set_id order by weight desc, key rows between unbounded preceding and 1 preceding), 0.0) as top, sum(weight) over (partition by set_id) as total from t0),
      th as (select set_id, arg_min(({k} - j) / (total - top), j) as thr from w where j < {k} and weight * (({k} - j) / (total - top)) <= 1 group by 1),
      n as (select set_id, case when count(*) > {k} then any_value(thr) else 'infinity'::double end as thr from t0 left join th using (set_id) group by 1),
      po as (select t0.set_id, key, weight, d, u / weight as rank, thr as bound from (select *, {_u("d::varchar", "key")} as u from t0, range(1, {DRAWS + 1}) t(d)) t0 join n using (set_id) where u / weight < thr)"""


def _spans(spans: dict[str, list[tuple[str, str]]]) -> str:
    rows = " union all ".join(f"select '{s}' as set_id, key, 1.0::double as weight from o where " + " or ".join(f"(key >= {a} and key < {b})" for a, b in parts).replace(" div ", " // ") for s, parts in spans.items())
    return f"with o as (select o_orderkey as key, (select count(*) from orders) as n from orders) {rows}"


_PAIR = {"A": [("0", "n div 3")]}
_W1 = _PAIR | {"B": [("(n div 3 - n div 15)", "(n div 3 * 2 - n div 15)")]}
_W1L = _PAIR | {"B": [("(n div 3 - n * 3 div 10)", "(n div 3 * 2 - n * 3 div 10)")]}
_W2 = {f"S{j}": [("0", "(n div 30)"), (f"((n div 30) * {1 + 4 * j})", f"((n div 30) * {5 + 4 * j})")] for j in range(5)}
_W3D = {f"S{j}": [(f"({2 * j} * (n * 619 div 7500))", f"({2 * j + 2} * (n * 619 div 7500))")] for j in range(5)}
_W3O = {f"S{j}": [("0", "(5 * (n * 619 div 7500))"), (f"({5 + j} * (n * 619 div 7500))", f"({6 + j} * (n * 619 div 7500))")] for j in range(5)}
_W1S = _PAIR | {"B": [("(n div 3 - n div 150)", "(n div 3 * 2 - n div 150)")]}


def _het(share: str) -> dict:
    return {"A": [("0", "n div 3")], "B": [("n div 3", f"(n div 3 + n div 3 * {share})")]}


_HET = _het("0.1")

_DIRECT = f"with {_sketch(_periods(True), K, 'exponential')} select set_id, pos::int as pos, key, round(rank, 8) as rank, {_FIN} from sk"
_LINKS = "select distinct set_id, page_id as key, length(html)::double as weight from (select page_id, html, unnest(list_distinct(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) as set_id from pages)"
_DOCS = "select distinct doc_id::varchar as set_id, unnest(list_distinct(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+'))) as key, 1.0::double as weight from documents"
_NODES = "[" + ", ".join(f"{{'z': {z!r}, 'w': {w!r}}}" for z, w in unit_nodes(64)) + "]"
_MIMIC = f"""lx as (select *, case when isinf(bound) then 0.0 else weight * (bound - rank) end as own from comb),
      la as (select query_id, sum(own) as alls, count(*) as l, sum(weight) as w from lx group by 1),
      le as (select *, list_sum([t.w * exp((l - 1) * ln(t.z) - alls * (1 - t.z)) for t in {_NODES}]) as e from la),
      rho as (select lx.*, case when isinf(bound) then weight / le.w when alls <= 0 then 1.0 / l else e + own / alls * (1 - l * e) end as rho from lx join le using (query_id))"""


_BEST = "least(greatest(case when n = 0 then 0.0 when isinf(bound) then total else root end, total), least(wa, wb))"


def _pair_known(f: str, extra: str = "", hi: str = "least(least(wa, wb), (wa + wb - otop) / 2)") -> str:
    """Two sets of known totals: the root of f and what follows from it."""
    base = f"{_pair_base()[5:]}, {_TOTALS}, {_shifted('comb', 'query_id', 'sets = 2')}{extra}, base1 as (select base0.*, ta.w as wa, tb.w as wb from base0 join pairs using (query_id) join tot ta on ta.set_id = a join tot tb on tb.set_id = b), base as (select *, top as lo, {hi} as hi from base1{' left join rest using (query_id)' if extra else ''})"
    text = _bisect(base, "query_id", f, "round(x, 6) as intersection, round(wa + wb - x, 6) as \"union\", round(x / (wa + wb - x), 6) as jaccard")
    return text.replace("from base join solved using (query_id)", f"from (select *, {_BEST} as x from base join solved using (query_id))")


_ONLY = """, on0 as (select query_id, mem[1] = a as ina, weight, coalesce(sum(weight) over (partition by query_id, mem[1] = a order by rank, key rows between unbounded preceding and 1 preceding), 0.0) as s from comb join pairs using (query_id) where sets = 1),
      rest as (select query_id, coalesce(list(s) filter (where ina), []) as onlya, coalesce(list(s) filter (where not ina), []) as onlyb, coalesce(max(s) filter (where ina), 0.0) as topa, coalesce(max(s) filter (where not ina), 0.0) as topb from on0 group by 1)"""


def _union_known(start: str, condition: str = "true") -> str:
    """query_id, estimate from known totals; start: the CTEs up to av."""
    base = f"""{start[5:]}, {_TOTALS}, pl as (select *, dense_rank() over (partition by query_id order by bound, set_id) as place from av),
      po as (select *, query_id::varchar || '/' || set_id as kk, place = max(place) over (partition by query_id, key) and ({condition}) as fits from pl),
      {_shifted('po', 'kk', 'fits')}, base1 as (select base0.*, w from base0 join tot on set_id = split_part(kk, '/', 2)), {_KNOWN[0]}"""
    return f"select split_part(kk, '/', 1)::bigint as query_id, sum(x) as estimate from ({_bisect(base, 'kk', _KNOWN[1], _KNOWN[2] + ' as x')}) group by 1"


_SAME_NODES = "[" + ", ".join(f"{{'z': {z!r}, 'w': {w!r}}}" for z, w in unit_nodes(128)) + "]"


def _log_expm1(x: str) -> str:
    return f"(case when {x} > 30 then {x} else ln(exp(least({x}, 30)) - 1) end)"


_SAME = f"""sx as (select comb.*, t.z, t.w as q, weight * bound as x from comb, (select unnest({_SAME_NODES}) as t) where not isinf(bound)),
      sg as (select *, {_log_expm1("(x * z)")} - {_log_expm1("x")} as lg, ln(x) + x * z - {_log_expm1("x")} as ld from sx),
      sr as (select query_id, key, sum(q * exp(ld + alls - lg)) as rho from (select *, sum(lg) over (partition by query_id, z) as alls from sg) group by 1, 2),
      rho as (select comb.*, case when isinf(bound) then weight / sum(weight) over (partition by query_id) else sr.rho / sum(sr.rho) over (partition by query_id) end as rho from comb left join sr using (query_id, key))"""


EXP = "exponential"
_UNION_ML = _bisect(f"{_base('short')[5:]}, {_shifted('comb', 'query_id', 'true')}, base as (select *, list_append(shifts, total) as terms, total as lo, total + (n + 1) / bound as hi from base0)", "query_id", f"{_recip('base.terms', 'X')} - base.bound", "case when isinf(bound) then total else root end as estimate")


def _hop(n: int) -> str:
    reach = {0: "select node::varchar as set_id, key from items", 1: "select node::varchar as set_id, key from items union select src::varchar, key from edges join items on dst = node"}
    if n < 2:
        return reach[n]
    return f"select set_id, key from ({reach[1]}) union select src::varchar, key from edges join ({reach[1]}) z on z.set_id = dst::varchar"


_GRAPH = """near as (select distinct l_orderkey, l_suppkey from lineitem where l_orderkey in (select o_orderkey from orders where date_diff('day', date '1995-01-01', o_orderdate::date) < 7)),
      edges as (select distinct x.l_suppkey as src, y.l_suppkey as dst from near x join near y on x.l_orderkey = y.l_orderkey and x.l_suppkey <> y.l_suppkey),
      items as (select distinct l_suppkey as node, l_partkey as key from lineitem)"""

ORACLES = {
    "flagship": f"with {_sketch(_periods(False).replace('distinct', 'distinct'), K, 'exponential')}, qs as (select 0 as query_id, 'p' || i::varchar as set_id from range(5) t(i)), {_AT}, {_comb('long')} select round(sum({_adj()}), 6) as estimate, count(*) as n_sampled, 'long' as combo, (select count(distinct key) from m)::double as exact from comb",
    "est_links_at_least": f"with {_sketch(_LINKS, K, 'priority')}, qs as (select distinct 1::bigint as query_id, set_id from m), {_AT}, lows as (select min(bound) as low from av), z as (select key, any_value(weight) as weight, count(distinct set_id) as sets, any_value(low) as bound from av, lows where rank < low group by 1) select 1::bigint as query_id, round(sum(case when sets >= 2 then {_adj('priority')} else 0 end), 6) as estimate from z",
    "est_event_days": f"with {_sketch('select distinct event_type || $$/$$ || strftime(ts, $$%Y-%m-%d$$) as set_id, user_id as key, 1.0::double as weight from events', 32, 'uniform')}, qs as (select 1 as query_id, t || '/' || x as set_id from (values ('click'), ('purchase')) a(t), (values ('2024-01-02'), ('2024-01-03')) b(x)), {_AT}, {_comb('short', attrs='')}, z as (select {_adj('uniform')} as adj, len([s for s in mem if s like 'click/%']) > 0 and len([s for s in mem if s like 'purchase/%']) > 0 as c from comb) select round(coalesce(sum(case when c then adj else 0 end), 0.0), 6) as estimate, count(*) filter (where c) as n_sampled from z",
    "rank_exponential": f"select o_orderkey as key, round(-ln({_u(repr(str(SEED)), 'o_orderkey')}) / {_skew('o_orderkey')}, 8) as rank from orders",
    "rank_priority": f"select o_orderkey as key, round({_u(repr(str(SEED)), 'o_orderkey')} / {_skew('o_orderkey')}, 8) as rank from orders",
    "rank_convert": f"select o_orderkey as key, round({_u(repr(str(SEED)), 'o_orderkey')} / {_skew('o_orderkey')}, 8) as rank from orders",
    "bottom_k_prefiltered": _DIRECT,
    "sketch_merge": _DIRECT,
    "bottom_k_vectors": f"with {_sketch('select distinct $$v$$ || label::varchar as set_id, vec_id as key, 1.0::double as weight from embeddings', K_SMALL, 'uniform')} select set_id, pos::int as pos, key, {_FIN} from sk",
    "sketch_rollup": f"with {_sketch('select distinct case when set_id < $$p2$$ then $$early$$ else $$late$$ end as set_id, key, weight from (' + _periods(True) + ')', K, 'exponential')} select set_id, pos::int as pos, key, {_FIN} from sk",
    "k_mins": f"with m as ({_periods(True)}), x as (select set_id, key, weight, j, -ln({_u(repr(f'{SEED}/') + ' || j::varchar', 'key')}) / weight as rank from m, range(1, {K_SMALL + 1}) t(j)) select set_id, j, arg_min(key, rank) as key, round(min(rank), 8) as min_rank from x group by 1, 2",
    "poisson_fixed": f"with m as ({_periods(True)}) select set_id, key, round(u / weight, 8) as rank from (select *, {_u(repr(str(SEED)), 'key')} as u from m) where u / weight < 0.002",
    "poisson_expected_k_ipps": f"""with m as ({_periods(True)}), w as (select *, row_number() over (partition by set_id order by weight desc, key) - 1 as j, coalesce(sum(weight) over (partition by set_id order by weight desc, key rows between unbounded preceding and 1 preceding), 0.0) as top, sum(weight) over (partition by set_id) as total from m),
      t as (select set_id, arg_min(({K} - j) / (total - top), j) as thr from w where j < {K} and weight * (({K} - j) / (total - top)) <= 1 group by 1),
      n as (select set_id, case when count(*) > {K} then any_value(thr) end as thr from m left join t using (set_id) group by 1)
      select set_id, key, round(thr, 8) as threshold from (select m.*, {_u(repr(str(SEED)), 'key')} as u, thr from m join n using (set_id)) where thr is null or u / weight < thr""",
    **{f"bottom_k_{short}": f"with {_sketch(_buyers(None), K_SMALL, family)} select set_id, pos::int as pos, key, round(rank, 8) as rank, {_FIN} from sk" for short, family in (("exp", "exponential"), ("pri", "priority"), ("uniform", "uniform"))},
    **{f"{name}": f"{_base(kind)} select query_id, key, {_FIN}, sets from comb" for name, kind in (("union_sketch", "union"), ("short_combination", "short"), ("long_combination", "long"))},
    **{f"adj_{kind}": f"{_base(kind)} select query_id, key, round({_adj()}, 6) as adj from comb" for kind in ("union", "short", "long")},
    **{f"adj_{kind}_priority": f"{_base(kind, 'priority')} select query_id, key, round({_adj('priority')}, 6) as adj from comb" for kind in ("short", "long")},
    **{f"adj_poisson_{kind}": f"with m as ({_periods(True)}), sk as (select *, 0.002::double as bound from (select *, u / weight as rank from (select *, {_u(repr(str(SEED)), 'key')} as u from m)) where rank < 0.002), {_FIRST}, {_AT}, {_comb(kind)} select query_id, key, round({_adj('priority')}, 6) as adj from comb" for kind in ("short", "long")},
    "long_membership": f"{_base('long')}, bs as (select query_id, set_id, any_value(bound) as sb from av group by 1, 2) select query_id, key, set_id, case when list_contains(mem, set_id) then 'in' when rank <= sb then 'out' else 'unknown' end as state from comb join bs using (query_id)",
    "est_union_size": f"with {_sketch(_periods(False), K, 'uniform')}, {_FIRST}, {_AT}, " + ", ".join(f"e_{k} as (with {_comb(k)} select query_id, sum({_adj('uniform')}) as e from comb group by 1)" for k in ("union", "short", "long")) + ", x as (select query_id, count(distinct key)::double as exact from m join qs using (set_id) group by 1) select query_id, exact, round(e_union.e, 6) as \"union\", round(e_short.e, 6) as short, round(e_long.e, 6) as long from x join e_union using (query_id) join e_short using (query_id) join e_long using (query_id)",
    "est_intersection": f"{_base('short')} select query_id, round(sum(case when sets = query_id then {_adj()} else 0 end), 6) as estimate from comb group by 1",
    "est_difference": _pair_sql("round(d, 6) as difference"),
    "est_hamming": _pair_sql("round(us - i, 6) as hamming"),
    "est_hamming_mixed": _pair_sql("round(u - i, 6) as hamming"),
    "est_pair": _pair_sql('round(u, 6) as "union", round(i, 6) as intersection, round(i / us, 6) as jaccard'),
    "est_intersection_ie": f"{_pair_base(kind='long')}, {_TOTALS}, l as (select query_id, sum({_adj()}) as u from comb group by 1) select query_id, round(ta.w + tb.w - u, 6) as intersection from l join pairs using (query_id) join tot ta on ta.set_id = a join tot tb on tb.set_id = b",
    "est_at_least_q": _estimates([(1, "sets >= 2", "short", 5), (2, "sets >= 3", "short", 5)]),
    "est_attr_filtered": _estimates([(1, _B, "long", 5), (2, f"not ({_B})", "long", 2)]),
    "est_sum_h": f"{_base('long')} select query_id, round(sum({_adj()} * (key % 7)::double / weight), 6) as estimate from comb group by 1",
    "est_ratio": f"{_base('long')} select query_id, round(sum(case when {_B} then {_adj()} else 0 end) / sum({_adj()}), 6) as estimate from comb group by 1",
    "est_mean_variance": f"{_base('long')}, s as (select query_id, sum(adj) as w, sum(adj * h) as a, sum(adj * h * h) as b from (select query_id, {_adj()} as adj, (key % 7)::double as h from comb where {_B}) group by 1) select query_id, round(a / w, 6) as mean, round(b / w - (a / w) ** 2, 6) as variance from s",
    "est_confidence": f"with {_sketch(_BRANDS, 256, 'uniform')}, {_TOTALS}, pairs as (select i as query_id, 'Brand#' || i::varchar as a, 'Brand#' || (i + 1)::varchar as b from range(1, 6) t(i)), {_PAIR_SETS}, {_AT}, {_comb('short', attrs='')} select query_id, round(sum(case when sets = 2 then {_adj('uniform')} else 0 end) / any_value(w), 6) as confidence from comb join pairs using (query_id) join tot on tot.set_id = b group by 1",
    "est_brand_rule": f"with {_sketch(_BRANDS, 256, 'uniform')}, qs as (select 0 as query_id, unnest(['Brand#1', 'Brand#2', 'Brand#3']) as set_id), {_AT}, {_comb('short', attrs=', any_value(lines) as lines')} select round(coalesce(sum(case when c then adj else 0 end), 0), 6) as estimate, count(*) filter (where c) as n_sampled, 'short' as combo from (select {_adj('uniform')} as adj, ((list_contains(mem, 'Brand#1') or list_contains(mem, 'Brand#2')) and list_contains(mem, 'Brand#3') and lines <= 3) as c from comb)",
    "est_weight_k_mins": f"with m as ({_periods(True)}), x as (select set_id, j, min(-ln({_u(repr(f'{SEED}/') + ' || j::varchar', 'key')}) / weight) as rank from m, range(1, {K + 1}) t(j) group by 1, 2), {_FIRST}, u as (select query_id, j, min(rank) as rank from x join qs using (set_id) group by 1, 2) select query_id, round({K - 1}.0 / sum(rank), 6) as estimate from u group by 1",
    "est_intersection_uncoordinated": f"with a as (with {_sketch('select * from (' + _periods(True) + ') where set_id = $$p0$$', 256, 'exponential', repr('1'))} select key, weight, {_p('exponential')} as p from sk), b as (with {_sketch('select * from (' + _periods(True) + ') where set_id = $$p1$$', 256, 'exponential', repr('2'))} select key, {_p('exponential')} as p from sk) select round(coalesce(sum(weight / (a.p * b.p)), 0), 6) as estimate from a join b using (key)",
    "est_baskets": f"with {_sketch('select distinct $$c$$ || o_custkey::varchar as set_id, l_partkey as key, p_retailprice as weight, p_type from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey', K_SMALL, 'priority')}, qs as (select 1 as query_id, 'c' || c_custkey::varchar as set_id from customer where c_mktsegment = 'BUILDING' and c_nationkey < 5), {_AT}, {_comb('long', attrs=', any_value(p_type) as p_type')} select round(sum(case when p_type = 'PROMO' then adj else 0 end), 6) as estimate, count(*) filter (where p_type = 'PROMO') as n_sampled, round(sqrt(sum(case when p_type = 'PROMO' then adj * adj * (1 - p) else 0 end)), 6) as std_error from (select *, {_p('priority')} as p, {_adj('priority')} as adj from comb)",
    "jaccard_union_uniform": f"{_pair_base('uniform', False, 'union')} select query_id, round(count(*) filter (where sets = 2) / count(*)::double, 6) as jaccard from comb group by 1",
    "jaccard_short_uniform": f"{_pair_base('uniform', False, 'short')} select query_id, round(count(*) filter (where sets = 2) / count(*)::double, 6) as jaccard from comb group by 1",
    "jaccard_k_mins": f"with m as ({_periods(False)}), x as (select set_id, j, min(-ln({_u(repr(f'{SEED}/') + ' || j::varchar', 'key')}) / weight) as rank from m, range(1, {K + 1}) t(j) group by 1, 2), {_PAIRS} select query_id, round(count(*) filter (where x.rank = y.rank) / {K}.0, 6) as jaccard from pairs join x on x.set_id = a join x y on y.set_id = b and y.j = x.j group by 1",
    "jaccard_weighted_mimic_exact": f"{_pair_base()}, {_MIMIC} select query_id, round(sum(case when sets = 2 then rho else 0 end), 6) as jaccard from rho group by 1",
    **{f"rho_mimic_exact_{kind}": f"{_base(kind)}, {_MIMIC} select query_id, round(sum(case when {_B} then rho else 0 end), 6) as share, round(sum(rho), 6) as total from rho group by 1" for kind in ("short", "union")},
    "naive_fractions": f"{_base('short')} select query_id, round(sum(case when {_B} then weight else 0 end) / sum(weight), 6) as by_weight, round(count(*) filter (where {_B}) / count(*)::double, 6) as by_count from comb group by 1",
    "ml_union": _bisect(f"{_base('short')[5:]}, {_shifted('comb', 'query_id', 'true')}, base as (select *, list_append(shifts, total) as terms, total as lo, total + (n + 1) / bound as hi from base0)", "query_id", f"{_recip('base.terms', 'X')} - base.bound", "round(case when isinf(bound) then total else root end, 6) as estimate"),
    "ml_subset": _bisect(f"{_base('short')[5:]}, {_shifted('comb', 'query_id', _B)}, base as (select *, top as lo, top + n / bound as hi from base0)", "query_id", f"{_recip('base.shifts', 'X')} - base.bound", "round(case when n = 0 then 0.0 when isinf(bound) then total else root end, 6) as estimate"),
    "ml_single_known": _bisect(f"{_sketch(_periods(True), K, 'exponential')}, {_TOTALS}, {_shifted('sk', 'set_id', _B)}, base1 as (select * from base0 join tot using (set_id)), {_KNOWN[0]}", "set_id", _KNOWN[1], f"round({_KNOWN[2]}, 6) as estimate"),
    "ml_intersection_known": _bisect(f"{_pair_base()[5:]}, {_TOTALS}, {_shifted('comb', 'query_id', 'sets = 2')}, base1 as (select base0.*, ta.w as wa, tb.w as wb from base0 join pairs using (query_id) join tot ta on ta.set_id = a join tot tb on tb.set_id = b), base as (select *, top as lo, least(least(wa, wb), (wa + wb - otop) / 2) as hi from base1)", "query_id", f"{_recip('base.shifts', 'X')} - 2 * {_recip('base.oshifts', 'base.wa + base.wb - 2 * X')} + base.bound", "round(x, 6) as intersection, round(wa + wb - x, 6) as \"union\", round(x / (wa + wb - x), 6) as jaccard").replace("from base join solved using (query_id)", "from (select *, least(greatest(case when n = 0 then 0.0 when isinf(bound) then total else root end, total), least(wa, wb)) as x from base join solved using (query_id))"),
    "ml_intersection_printed": _pair_known(f"{_recip('base.shifts', 'X')} - {_recip('list_sort(base.oshifts)[2:]', 'base.wa + base.wb - 2 * X')}"),
    "ml_intersection_three_part": _pair_known(f"{_recip('base.shifts', 'X')} - {_recip('coalesce(base.onlya, [])', 'base.wa - X')} - {_recip('coalesce(base.onlyb, [])', 'base.wb - X')} + base.bound", _ONLY, "least(least(wa, wb), least(wa - coalesce(topa, 0), wb - coalesce(topb, 0)))"),
    "ml_union_known": f"select query_id, round(estimate, 6) as estimate from ({_union_known(f'with {_sketch(_periods(True), K, EXP)}, {_FIRST}, {_AT}')})",
    "ml_union_known_filtered": f"select query_id, round(estimate, 6) as estimate from ({_union_known(f'with {_sketch(_periods(True), K, EXP)}, {_FIRST}, {_AT}', _B)})",
    "ml_intersection_from_union": f"with m as ({_periods(True)}), {_PAIRS}, {_TOTALS} select query_id, round(ta.w + tb.w - estimate, 6) as estimate from ({_union_known(f'with {_sketch(_periods(True), K, EXP)}, {_PAIRS}, {_PAIR_SETS}, {_AT}')}) join pairs using (query_id) join tot ta on ta.set_id = a join tot tb on tb.set_id = b",
    "rho_same_keys": f"{_base('short')}, {_SAME} select query_id, round(sum(case when {_B} then rho else 0 end), 6) as share, round(sum(rho), 6) as total from rho group by 1",
    "jaccard_weighted_same_keys": f"{_pair_base()}, {_SAME} select query_id, round(sum(case when sets = 2 then rho else 0 end), 6) as jaccard from rho group by 1",
    "rho_to_weight": f"with totals as ({_UNION_ML}), shares as ({_base('short')}, {_MIMIC} select query_id, sum(case when {_B} then rho else 0 end) as share from rho group by 1) select query_id, round(share * estimate, 6) as estimate from shares join totals using (query_id)",
    "poisson_threshold_exp": _bisect(f"m as ({_periods(True)}), base as (select set_id, list(weight) as ws, count(*) as n, 0.0 as lo, 50.0 / min(weight) as hi from m group by 1)", "set_id", f"{K} - list_sum([1 - exp(-w * X) for w in base.ws])", f"round(case when n <= {K} then 'infinity'::double else root end, 8) as threshold"),
    "similar_pairs_quality": f"""with {_sketch(_DOCS, 2 * K_SMALL, 'uniform')}, sz as (select set_id, count(*) as n from m group by 1), cm as (select x.set_id as a, y.set_id as b, count(*) as c from m x join m y on x.key = y.key and x.set_id < y.set_id group by 1, 2),
      real as (select a, b from cm join sz sa on sa.set_id = a join sz sb on sb.set_id = b where c / (sa.n + sb.n - c)::double >= 0.5),
      c as (select x.set_id as a, y.set_id as b, least(x.bound, y.bound) as low, list(x.rank) as ranks from sk x join sk y on x.key = y.key and x.set_id < y.set_id group by 1, 2, 3), s as (select set_id, list(rank) as rs from sk group by 1),
      j as (select a, b, ranks, low, list_sort([r for r in list_distinct(list_concat(sa.rs, sb.rs)) if r < low]) as known from c join s sa on sa.set_id = a join s sb on sb.set_id = b),
      f as (select 'short' as method, a, b, ranks, known from j union all select 'union', a, b, ranks, known[:{2 * K_SMALL}] from j),
      g as (select method, a, b from f where len(known) > 0 and len(list_intersect(ranks, known)) / len(known)::double >= 0.5)
      select method, (select count(*) from real) as true_pairs, count(*) as reported, count(real.a) as correct, round(count(real.a) / count(*)::double, 6) as precision, round(count(real.a) / (select count(*) from real)::double, 6) as recall from g left join real using (a, b) group by 1""",
    "ml_rank_gaps": f"with {_sketch(_periods(True), K, 'exponential')} select set_id, key, round(rank - coalesce(lag(rank) over (partition by set_id order by rank, key), 0.0), 8) as gap, round(coalesce(sum(weight) over (partition by set_id order by rank, key rows between unbounded preceding and 1 preceding), 0.0), 6) as seen from sk",
    "exact_union": _exact("true"),
    "exact_intersection": _exact("list_contains(mem, 'p0') and list_contains(mem, 'p1')"),
    "exact_at_least_q": _exact("sets >= 2"),
    "exact_filtered": _exact(_B),
    "exact_jaccard": f"with m as ({_periods(True)}), {_PAIRS}, {_PAIR_SETS}, h as (select query_id, key, any_value(weight) as weight, count(distinct set_id) as sets from m join qs using (set_id) group by 1, 2) select query_id, round(sum(case when sets = 2 then weight else 0 end) / sum(weight), 6) as exact from h group by 1",
    "similar_pairs": f"""with {_sketch(_DOCS, K, 'uniform')}, c as (select x.set_id as a, y.set_id as b, least(x.bound, y.bound) as low, list(x.rank) as ranks from sk x join sk y on x.key = y.key and x.set_id < y.set_id group by 1, 2, 3),
      s as (select set_id, list(rank) as rs from sk group by 1),
      j as (select a, b, len([r for r in ranks if r < low]) as hit, len([r for r in list_distinct(list_concat(sa.rs, sb.rs)) if r < low]) as n from c join s sa on sa.set_id = a join s sb on sb.set_id = b)
      select a, b, round(hit / n::double, 6) as jaccard from j where n > 0 and hit / n::double >= 0.5""",
    "errors_w1": _errors(_spans(_W1), "uniform", pair=True),
    "errors_w1_small_overlap": _errors(_spans(_W1S), "uniform", pair=True),
    "errors_w1_k": _by("k", {str(k): _errors(_spans(_W1), "uniform", k) for k in (10, 50, 250)}),
    "errors_w1_many_draws": _errors(_spans(_W1), "uniform", draws=64),
    "errors_w2_i": _by("i", {str(i): _errors(_spans({f"S{j}": _W2[f"S{j}"] for j in range(i)}), "uniform") for i in (2, 3, 4, 5)}),
    "errors_w4_i": _by("i", {str(i): _errors(f"select set_id, key, weight from ({_periods(False)}) where set_id < 'p{i}'", "uniform") for i in (2, 3, 4, 5)}),
    "errors_w5_brand": _union_errors(_buyers(weight="1.0::double"), "uniform", ERROR_K, DRAWS),
    "errors_w5_all": _union_errors(_buyers(None, "1.0::double"), "uniform", K_SMALL, DRAWS),
    "errors_w5_documents": _union_errors(_DOCS, "uniform", K_SMALL, DRAWS),
    "errors_w16": _by("share", {f"'{f}'": _errors(_spans(_het(f)), "uniform") for f in ("1.0", "0.5", "0.1", "0.01")}),
    "errors_b8": f"select estimator, avg_rel_error, mean_size from ({_union_errors(_spans(_het('1.0')), 'uniform', ERROR_K, DRAWS)}) union all select 'union_of_size_l', avg_rel_error, mean_size from ({_union_errors(_spans(_het('1.0')), 'uniform', 2 * ERROR_K, DRAWS)}) where estimator = 'union'",
    "errors_k_mins": f"""with t0 as (select distinct set_id, key, weight from ({_spans(_W1)})), x as (select d::bigint as query_id, set_id, j, arg_min(key, -ln(u)) as key, min(-ln(u)) as rank from (select *, {_u("d::varchar || '/' || j::varchar", "key")} as u from t0, range(1, {DRAWS + 1}) t(d), range(1, {K_SMALL + 1}) s(j)) group by 1, 2, 3),
      m as (select query_id, j, min(rank) as rank, count(distinct key) as keys from x group by 1, 2), e as (select query_id, {K_SMALL - 1}.0 / sum(rank) as u, count(*) filter (where keys = 1)::double / {K_SMALL} as c from m group by 1),
      est as (select 'union' as measure, u as estimate from e union all select 'jaccard', c from e), {_TRUTH}
      select measure, 'k-mins' as estimator, round(avg(abs(estimate - exact) / exact), 6) as avg_rel_error from est join tr using (measure) group by 1 union all select measure, estimator, avg_rel_error from ({_errors(_spans(_W1), 'uniform', K_SMALL)}) where measure in ('union', 'jaccard')""",
    "errors_w14": f"""with {_draws(_periods(True), 'priority', ERROR_K, DRAWS)}, {_ipps(ERROR_K)}, """
    + ", ".join(f"e_{name} as (with av as (select d::bigint as query_id, z.* from {source} z), {_comb(kind, attrs='')} select query_id, sum({_adj('priority')}) as estimate, count(*) as size from comb group by 1)" for name, source, kind in (("order_short", "sk", "short"), ("order_long", "sk", "long"), ("poisson_short", "po", "short"), ("poisson_long", "po", "long")))
    + ", est as (" + " union all ".join(f"select '{e}' as estimator, d as query_id, coalesce(estimate, 0) as estimate, coalesce(size, 0) as size from range(1, {DRAWS + 1}) t(d) left join e_{e} on query_id = d" for e in ("order_short", "order_long", "poisson_short", "poisson_long")) + f"), {_TRUTH} select estimator, round(avg(abs(estimate - u) / u), 6) as avg_rel_error, round(avg(size), 6) as mean_size from est, tr0 group by 1",
    "sampling_variances": f"""with {_draws(_periods(True), 'priority', ERROR_K + 1, DRAWS)}, {_ipps(ERROR_K)}, z as (select 'priority' as estimator, split_part(set_id, '|', 2) as set_id, weight, {_adj('priority')} as adj from sk union all select 'poisson', set_id, weight, {_adj('priority')} from po)
      select set_id, estimator, round(any_value(sq) + sum(adj * adj - 2 * weight * adj) / {DRAWS}, 2) as sum_of_variances from z join (select set_id, sum(weight * weight) as sq from t0 group by 1) using (set_id) group by 1, 2""",
    "law_measures": f"with {_draws('select * from (' + _periods(True) + ') where set_id < $$p2$$', 'exponential', ERROR_K, DRAWS)}, av as (select d::bigint as query_id, sk.* from sk), " + ", ".join(f"c_{k} as (with {_comb(k, ERROR_K, '')} select '{k}' as estimator, query_id, weight, {_adj()} as adj from comb)" for k in ("union", "short", "long")) + f", z as (select * from c_union union all select * from c_short union all select * from c_long), {_TRUTH}, e as (select estimator, query_id, sum(adj) as s from z group by 1, 2), v as (select estimator, sum(adj * adj - 2 * weight * adj) / {DRAWS} as v from z group by 1) select estimator, round(avg(s) / (select u from tr0), 6) as mean_ratio, round(var_pop(s) / avg(s) ** 2, 6) as cv2, round(any_value(v) + (select sum(weight * weight) from h), 2) as sum_of_variances from e join v using (estimator) group by 1",
    "law_covariance": f"with {_draws('select $$n$$ as set_id, n_nationkey::bigint as key, ' + _skew('n_nationkey') + ' as weight from nation', 'exponential', K_SMALL, 8 * DRAWS)}, z as (select d, key, weight, {_adj()} as adj from sk) select a.key as i, b.key as j, round(sum(a.adj * b.adj) / {8 * DRAWS} - any_value(a.weight) * any_value(b.weight), 6) as covariance from z a join z b on a.d = b.d and a.key < b.key group by 1, 2",
    "law_partition": f"""with t0 as (select distinct set_id, key, weight from ({_periods(True)})), a as (with {_draws(_periods(True), 'exponential', K, DRAWS)} select 'whole' as estimator, weight, {_adj()} as adj from sk),
      b as (with {_draws('select set_id || $$#$$ || (key % 4)::varchar as set_id, key, weight from (' + _periods(True) + ')', 'exponential', K // 4, DRAWS)} select 'parts' as estimator, weight, {_adj()} as adj from sk)
      select estimator, round((select sum(weight * weight) from t0) + sum(adj * adj - 2 * weight * adj) / {DRAWS}, 2) as sum_of_variances from (select * from a union all select * from b) group by 1""",
    "est_terms_weighted": f"""with dt as (select doc_id, lang, unnest(list_distinct(regexp_extract_all(lower(coalesce(text, '')), '[a-z]+'))) as key from documents), df as (select key, ln(1 + (select count(*) from documents)::double / count(*)) as weight from dt group by 1),
      {_sketch('select distinct lang as set_id, key, weight, length(key) as length from dt join df using (key) where lang is not null', 256, 'exponential')}, pairs as (select * from (values (1::bigint, 'de', 'en'), (2::bigint, 'de', 'es'), (3::bigint, 'de', 'fr'), (12::bigint, 'en', 'es'), (13::bigint, 'en', 'fr'), (23::bigint, 'es', 'fr')) t(query_id, a, b)),
      {_PAIR_SETS}, {_AT}, {_comb('short', attrs=', any_value(length) as length')}, {_MIMIC} select query_id, round(sum(case when sets = 2 and length >= 5 then {_adj()} else 0 end), 6) as shared, round(sum(case when sets = 2 then {_adj()} else 0 end), 6) as all_shared, round(sum(case when sets = 2 then rho else 0 end), 6) as jaccard from rho group by 1""",
    "est_periods_restricted": f"with {_sketch(_periods(True), K, 'exponential')}, {_FIRST}, {_AT}, " + ", ".join(f"e_{k} as (with {_comb(k)} select query_id, sum(case when {_B} then {_adj()} else 0 end) as e from comb group by 1)" for k in ("union", "short", "long")) + f", x as (select query_id, sum(weight) as exact from (select distinct query_id, key, weight from m join qs using (set_id) where {_B}) group by 1) select query_id, round(exact, 6) as exact, round(e_union.e, 6) as \"union\", round(e_short.e, 6) as short, round(e_long.e, 6) as long from x join e_union using (query_id) join e_short using (query_id) join e_long using (query_id)",
    "errors_w1_large_overlap": _errors(_spans(_W1L), "uniform"),
    "errors_w2": _errors(_spans(_W2), "uniform"),
    "errors_w3_disjoint": _errors(_spans(_W3D), "uniform"),
    "errors_w3_overlap": _errors(_spans(_W3O), "uniform"),
    "errors_w4": _errors(f"select set_id, key, weight from ({_periods(False)})", "uniform"),
    "errors_w13_weighted": _errors(f"select set_id, key, weight from ({_periods(True)})", "exponential"),
    "short_share": f"with {_sketch(_spans(_HET), ERROR_K, 'uniform')}, lows as (select min(bound) as low from sk), n as (select set_id, count(*) as n from sk group by 1) select set_id, round(count(*) / any_value(n)::double, 6) as share from sk join n using (set_id) where rank < (select low from lows) group by 1",
    "neighborhood_sketch": f"with {_GRAPH}, " + ", ".join(f"h{n} as (with {_sketch('select distinct set_id, key, 1.0::double as weight from (' + _hop(n) + ')', K_SMALL, 'uniform')} select {n}::bigint as hop, set_id, pos::int as pos, key, {_FIN} from sk)" for n in range(3)) + " select * from h0 union all select * from h1 union all select * from h2",
    "stream_bottom_k": f"with {_sketch('select distinct event_type || $$/$$ || strftime(ts, $$%Y-%m-%d$$) as set_id, user_id as key, 1.0::double as weight from events', K_SMALL, 'uniform')} select set_id, pos::int as pos, key, {_FIN} from sk",
}
ORACLES = {name: sql for name, sql in ORACLES.items() if sql}
