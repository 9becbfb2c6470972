"""DuckDB texts that make the key sets, queries, profiles and designs again, each in its own way."""

from __future__ import annotations

from rangegate.functions.hashes import P, _seeded
from rangegate.operators.workload import GENERATED, ORIGIN, SETS, KeySet


def mix(seed: int, x: str) -> str:
    a, b, c = _seeded(seed)
    t = f"((({a}::bigint * (({x}) % {P})) % {P} + ({b}::bigint * ((({x}) // {P}) % {P})) % {P} + {c}) % {P})"
    t = f"((({t} * {t}) % {P} + {c}) % {P})"
    t = f"((({a}::bigint * {t}) % {P} + {b}) % {P})"
    return f"((({t} * {t}) % {P} + ({t} * {c}::bigint) % {P} + {a}) % {P})"


def wide(high: int, low: int, x: str) -> str:
    return f"(({mix(high, x)} << 31) | {mix(low, x)})"


def customer_codes(name: str) -> str:
    """Distinct codes hashed from the customers' keys."""
    code = _hashed(name, "c_custkey")
    return f"select distinct ({code})::bigint as code from customer where c_custkey is not null"


def event_queries(ks: KeySet, every: int) -> str:
    top = (1 << ks.bits) - 1
    return f"select qid, lo, least(lo + {mix(44, 'qid')} % {(1 << ks.long) - 1} + 2, {top}) as hi from (select event_id as qid, least(epoch_us(ts) - {ORIGIN}, {top}) as lo from events where event_id % {every} = 0 and ts is not null)"


def _hashed(name: str, x: str) -> str:
    if name == "u62":
        return wide(5, 6, x)
    return f"{1 << 61} + ({' + '.join(mix(10 + i, x) for i in range(12))} - {6 * P}) * 21474836 + {mix(30, x)} % 21474836"


def keys(name: str) -> str:
    ts = f"(epoch_us(ts) - {ORIGIN})"
    source = {
        "ts": f"select {ts} as code from events",
        "user_ts": f"select (user_id << 42) | {ts} as code from events",
        "val": "select (round(value * 100)::bigint << 17) | event_id as code from events",
        "line": "select l_orderkey * 8 + l_linenumber as code from lineitem",
        "price": "select round(l_extendedprice * 100)::bigint as code from lineitem",
        "u62": f"select {_hashed('u62', 'id')} as code from range({GENERATED}) as r(id)",
        "n62": f"select {_hashed('n62', 'id')} as code from range({GENERATED}) as r(id)",
    }[name]
    return f"select distinct code::bigint as code from ({source}) where code is not null"


def uniform(ks: KeySet, n: int, bits: int | None = None) -> str:
    r = 1 << (ks.long if bits is None else bits)
    return f"select qid, lo, lo + w as hi from (select id as qid, {wide(40, 41, 'id')} % {(1 << ks.bits) - r} as lo, {wide(42, 43, 'id')} % {max(1, r - 1)} + 2 as w from range({n}) as r(id))"


def correlated(ks: KeySet, n: int, bits: int | None = None) -> str:
    r, top = 1 << (ks.short if bits is None else bits), (1 << ks.bits) - 1
    return f"""select qid, lo, least(lo + {mix(44, 'qid')} % {max(1, r - 1)} + 2, {top}) as hi from (
      select qid, least(code + 1 + {mix(46, 'qid')} % {1 << ks.reach}, {top}) as lo from (
        select code, row_number() over (order by h, code) - 1 as qid from (select code, {mix(45, 'code')} as h from ({keys(ks.name)})) qualify qid < {n}))"""


def split(ks: KeySet, n: int) -> str:
    return f"select * from ({uniform(ks, n)}) where qid % 2 = 0 union all select * from ({correlated(ks, n)}) where qid % 2 = 1"


def queries(ks: KeySet, kind: str, n: int) -> str:
    if kind in ("uniform", "correlated", "split"):
        return {"uniform": uniform, "correlated": correlated, "split": split}[kind](ks, n)
    if kind == "points":
        return f"select qid, lo, lo as hi from ({uniform(ks, n)})"
    if kind == "mixed":
        return f"select qid, lo, case when qid % 2 = 0 then lo else hi end as hi from ({uniform(ks, n)})"
    if kind == "present":
        return f"select code as qid, code as lo, code as hi from ({keys(ks.name)}) order by {mix(48, 'code')}, code limit {n}"
    return f"select code as qid, code as lo, least(code + 2 + {mix(44, 'code')} % {max(1, (1 << ks.short) - 1)}, {(1 << ks.bits) - 1}) as hi from ({keys(ks.name)}) where {mix(47, 'code')} % 11 = 0"


def kept_keys(ks: KeySet, kind: str) -> str:
    return f"select code from ({keys(ks.name)})" + (f" where {mix(47, 'code')} % 11 <> 0" if kind == "real" else "")


def lcp(k: int, a: str, b: str) -> str:
    return f"(case when {b} is null then 0 when {a} = {b} then {k} else {k} - length(bin(xor({a}, {b}))) end)"


def profile(ks: KeySet, kind: str, n: int) -> str:
    """CTEs k, q, p."""
    k = ks.bits
    return f"""k as materialized ({kept_keys(ks, kind)}), q as materialized ({queries(ks, kind, n)}), pr as (
      select q.qid, q.lo, q.hi, k.code as pred from q asof left join k on q.lo > k.code
    ), ps as (
      select pr.*, k.code as succ from pr asof left join k on pr.lo <= k.code
    ), p as materialized (
      select *, greatest(lcp_l, lcp_r) as near from (
        select *, {lcp(k, 'lo', 'pred')}::integer as lcp_l, {lcp(k, 'hi', 'succ')}::integer as lcp_r, coalesce(succ > hi, true) as is_empty from ps))"""


def counts(ks: KeySet) -> str:
    """CTE n of (l, n) from k."""
    return f"n as materialized (select l::integer as l, count(distinct code >> ({ks.bits} - l)::integer) as n from k, range(1, {ks.bits + 1}) as r(l) group by l)"


def tries(ks: KeySet, bpk: float) -> str:
    """CTEs m (budget), t (l, dense_levels, bits), dep (feasible depths)."""
    return f"""m as (select floor(count(*) * {bpk})::bigint as m from k), n0 as (select l, n from n union all select 0, 1), lev as (
      select d.l, v.level, v.level * 8 as s, least(v.level * 8 + 8, d.l) as e from n d, range(0, 8) as v(level) where v.level * 8 < d.l
    ), cost as (
      select lev.l, level, a.n * (2 * (1::bigint << (e - s)::integer) + 1) as dense, b.n * (e - s + 2) as sparse from lev join n0 a on a.l = s join n0 b on b.l = e
    ), cut as (
      select l, c, coalesce(sum(dense) filter (where level < c), 0) + coalesce(sum(sparse) filter (where level >= c), 0) as raw from cost, range(0, 9) as r(c) where c <= ceil(l / 8.0) group by l, c
    ), t as (
      select l, arg_min(c, (raw, c))::integer as dense_levels, ceil(min(raw) * 1.0625)::bigint as bits from cut group by l
    ), dep as materialized (select l as l1, bits as trie from t, m where bits <= m.m union all select 0, 0)"""


BLOOM = "case when {m} <= 0 then 1.0 else pow(1 - exp(-{h} * {n}::double / {m}), {h}) end"


def bloom(m: str, n: str) -> str:
    h = f"least(greatest(ceil(({m}) / ({n})::double * ln(2)), 1), 32)"
    return BLOOM.format(m=f"({m})", n=f"({n})", h=h)


def evidence(ks: KeySet, where: str = "true", binned: bool = True) -> str:
    """CTE ev of (l1, l2, bin, n_queries, avg_probes) from p and dep."""
    k = ks.bits
    return f"""x as (
      select p.*, dep.l1, g.l2, lo >> ({k} - l1)::integer as a0, hi >> ({k} - l1)::integer as a1, lo >> ({k} - l2)::integer as f, hi >> ({k} - l2)::integer as z from p, dep, range(1, {k + 1}) as g(l2) where is_empty and l2 > l1 and {where}
    ), y as (
      select *, case when a0 = a1 then near >= l1 else lcp_l >= l1 end as hl, a0 <> a1 and lcp_r >= l1 as hr,
        least(z, ((a0 + 1) << (l2 - l1)::integer) - 1) - f + 1 as nl, z - greatest(f, a1 << (l2 - l1)::integer) + 1 as nr from x
    ), c as (
      select l1, l2, case when near >= l2 then -1 else case when hl then nl else 0 end + case when hr then nr else 0 end end as pc from y
      union all select l1, 0, case when near >= l1 then -1 else 0 end from p, dep where is_empty and l1 > 0 and {where.replace('l2', '0')}
    ), ev as materialized (
      select l1::integer as l1, l2::integer as l2, {"case when pc <= 0 then pc else length(bin(pc)) end" if binned else "pc"}::bigint as bin, count(*) as n_queries, avg(case when pc < 0 then 0 else pc end)::double as avg_probes from c group by all
    )"""


def rates(mode: str = "exact") -> str:
    """CTE fp of (l1, l2, bloom, p, exp_fpr) from ev, n, m, dep."""
    some = "1 - pow(1 - p, avg_probes)" if mode == "exact" else "least(1.0, p * avg_probes)"
    return f"""siz as (
      select l1, l as l2, m - trie as bloom, {bloom('m - trie', 'n')} as p from dep, n, m where l > l1 and m - trie >= 1 union all select l1, 0, 0, 0.0 from dep where l1 > 0
    ), fp as materialized (
      select ev.l1, ev.l2, any_value(bloom)::bigint as bloom, any_value(p)::double as p,
        round(sum(n_queries * case when bin = -1 then 1.0 when p >= 1 then (avg_probes > 0)::integer else {some} end) / sum(n_queries), 9) as exp_fpr
      from ev join siz using (l1, l2) group by ev.l1, ev.l2
    )"""


def designs(name: str, kind: str, n: int, bpk: float, where: str = "true", binned: bool = True, mode: str = "exact") -> str:
    ks = SETS[name]
    return f"with {profile(ks, kind, n)}, {counts(ks)}, {tries(ks, bpk)}, {evidence(ks, where, binned)}, {rates(mode)}"


def dyadic(queries: str, bits: int) -> str:
    """qid, level, block: aligned blocks inside a query whose parent is not inside."""
    return f"""select qid, j::integer as level, b as block from (
      select qid, lo, hi, j, unnest([((lo + (1::bigint << j::integer) - 1) >> j::integer), ((hi + 1) >> j::integer) - 1]) as b from ({queries}), range({bits + 1}) as r(j)
    ) where b >= 0 and (b << j::integer) >= lo and ((b + 1) << j::integer) - 1 <= hi
      and not (((b >> 1) << (j + 1)::integer) >= lo and (((b >> 1) + 1) << (j + 1)::integer) - 1 <= hi) group by all"""
