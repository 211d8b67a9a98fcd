"""DuckDB SQL that computes the filters' answers anew, from the same hash functions and nothing else."""

from __future__ import annotations

from sieveset.functions.hashing import mix64_sql
from sieveset.kernels.filters import BLOCK_MULTIPLIERS
from sieveset.operators.spec import ALTERNATE, CELL0, CELL1, CELL2, PLACE, PRINT, FilterSpec, attempt_seed, role_seed

M32 = (1 << 32) - 1
MEMBERS = "select o_orderkey as k from orders where o_orderstatus = 'F'"
OTHERS = "select o_orderkey as k from orders where o_orderstatus <> 'F'"
PROBES = "select distinct l_orderkey as k from lineitem"
PCTS = (0, 25, 50, 75, 100)


def mix(k: str, spec: FilterSpec, role: int) -> str:
    return mix64_sql(k, role_seed(attempt_seed(spec.seed, 0, 0), role))


def reduce(h: str, size: str) -> str:
    """High half of a hash to [0, size)."""
    return f"(((({h}) >> 32) * ({size})::uhugeint) >> 32)::bigint"


def cells(k: str, spec: FilterSpec) -> str:
    """c0, c1, c2, fp over a scalar ``c``."""
    seg = ("0", "c // 3", "2 * c // 3", "c")
    cols = [f"({seg[i]}) + {reduce(mix(k, spec, r), f'({seg[i + 1]}) - ({seg[i]})')} as c{i}" for i, r in enumerate((CELL0, CELL1, CELL2))]
    return ", ".join([*cols, f"({mix(k, spec, PRINT)} & {(1 << spec.fp_bits) - 1}::uhugeint)::bigint as fp"])


def xor_ctes(spec: FilterSpec, members: str = MEMBERS) -> str:
    """CTEs up to ``b(cell, val)``: the canonical peel by rounds and the assignment in reverse."""
    count = lambda part: ", ".join(f"count(*) over (partition by {part}c{i}) as n{i}" for i in range(3))
    return f"""
m as ({members}),
cfg as (select {spec.slack_hundredths} * count(*) // 100 + {spec.extra} as c, count(*) as n from m),
keys as materialized (select k, {cells('k', spec)} from m, cfg),
alive as (
  select k, c0, c1, c2, 0 as round from keys
  union all
  select k, c0, c1, c2, round + 1 from (
    select *, min(least(n0, n1, n2)) over () as least_n from (select *, {count('')} from alive))
  where least_n = 1 and n0 > 1 and n1 > 1 and n2 > 1),
peeled as materialized (
  select k, c0, c1, c2, round, case when n0 = 1 then c0 when n1 = 1 then c1 when n2 = 1 then c2 end as own
  from (select *, {count('round, ')}, max(round) over (partition by k) as last from alive) where round = last),
steps as materialized (
  select p.*, fp, max(p.round) over () - p.round as step from peeled p join keys using (k)),
b(cell, val, step) using key (cell) as (
  select -1::bigint, 0::bigint, -1::bigint
  union
  select s.own, xor(xor(s.fp, coalesce(b0.val, 0)), xor(coalesce(b1.val, 0), coalesce(b2.val, 0))), s.step::bigint
  from steps s join (select max(step) as at from b) cur on s.step = cur.at + 1
  left join recurring.b b0 on b0.cell = s.c0 left join recurring.b b1 on b1.cell = s.c1 left join recurring.b b2 on b2.cell = s.c2)"""


def reported_ctes(spec: FilterSpec, members: str = MEMBERS, probes: str = "q") -> str:
    """CTEs that end with ``reported(k)``, the keys of ``probes`` that the filter reports; ``q(k)`` must come before."""
    if spec.kind == "xor":
        look = " ".join(f"left join b b{i} on b{i}.cell = p.c{i}" for i in range(3))
        return f"""{xor_ctes(spec, members)},
asked as materialized (select k, {cells('k', spec)} from (select distinct k from {probes}), cfg),
reported as (select p.k from asked p {look}
  where xor(xor(coalesce(b0.val, 0), coalesce(b1.val, 0)), coalesce(b2.val, 0)) = p.fp)"""
    place = mix("k", spec, PLACE)
    head = f"m as ({members}), cfg as (select count(*) as n from m), a as (select distinct k from {probes})"
    if spec.kind == "bloom":
        bits = f"({spec.bits_per_key or 8} * n)::bigint" if float(spec.bits_per_key or 8).is_integer() else f"floor({spec.bits_per_key!r}::double * n)::bigint"
        pos = f"((((h >> 32) + i::uhugeint * (h & {M32}::uhugeint)) & {M32}::uhugeint) * greatest(1, {bits})::uhugeint >> 32)::bigint"
        return f"""{head},
hm as (select k, {place} as h from m), ha as (select k, {place} as h from a),
bits as (select distinct {pos} as bit from hm, cfg, range({spec.hashes}) t(i)),
reported as (select k from (select k, {pos} as bit from ha, cfg, range({spec.hashes}) t(i)) join bits using (bit) group by k having count(*) = {spec.hashes})"""
    if spec.kind == "blocked_bloom":
        tenths = round(10 * (spec.bits_per_key or 10.7))
        blocks = f"greatest(1, ({tenths} * n + 2559) // 2560)"
        multipliers = ", ".join(f"({j}, {x})" for j, x in enumerate(BLOCK_MULTIPLIERS))
        place_ = f"{reduce('h', blocks)} as block, word, ((((h & {M32}::uhugeint) * mult::uhugeint) & {M32}::uhugeint) >> 27)::bigint as bit"
        return f"""{head}, odd(word, mult) as (values {multipliers}),
hm as (select k, {place} as h from m), ha as (select k, {place} as h from a),
bits as (select distinct {place_} from hm, cfg, odd),
reported as (select k from (select k, {place_} from ha, cfg, odd) join bits using (block, word, bit) group by k having count(*) = 8)"""
    if spec.kind.startswith("cuckoo"):
        hundredths = round(100 * spec.load)
        buckets = f"greatest(1, (100 * n + {4 * hundredths - 1}) // {4 * hundredths})"
        if spec.kind.endswith("pow2"):
            buckets = f"(1::bigint << ceil(log2({buckets}))::int)"
        other = "xor(l1, ho)" if spec.kind.endswith("pow2") else "((nb - l1 - ho) % nb + nb) % nb"
        of = lambda t: f"select k, f, l1, {other} as l2 from (select k, f, nb, {reduce(place, 'nb')} as l1, {reduce(mix('f', spec, ALTERNATE), 'nb')} as ho from (select k, nb, greatest(1, ({mix('k', spec, PRINT)} & {(1 << spec.fp_bits) - 1}::uhugeint)::bigint) as f from {t}, (select {buckets} as nb from cfg)))"
        return f"""{head},
placed as (select distinct f, least(l1, l2) as lo, greatest(l1, l2) as hi from ({of('m')})),
reported as (select distinct k from ({of('a')}) x join placed p on p.f = x.f and p.lo = least(x.l1, x.l2) and p.hi = greatest(x.l1, x.l2))"""
    if spec.kind == "gcs":
        value = reduce(place, f"n * {1 << spec.fp_bits}")
        return f"{head}, stored as (select distinct {value} as v from m, cfg), reported as (select k from (select k, {value} as v from a, cfg) join stored using (v))"
    if spec.kind == "cqf":
        value = f"(({place}) >> (64 - greatest(1, ceil(log2(greatest(2, n / 0.95)))::int) - {spec.fp_bits})::uhugeint)::bigint"
        return f"{head}, stored as (select distinct {value} as v from m, cfg), reported as (select k from (select k, {value} as v from a, cfg) join stored using (v))"
    if spec.kind == "exact":
        return f"{head}, reported as (select k from a semi join m using (k))"
    raise ValueError(spec.kind)


def query_mix(members: str = MEMBERS, others: str = OTHERS, pcts: tuple[int, ...] = PCTS) -> str:
    """CTE ``q(hit_pct, k, is_member)``: shares of members and others by ascending key."""
    return f"""
rm as (select k, row_number() over (order by k) as r from ({members})),
ro as (select k, row_number() over (order by k) as r from ({others})),
qn as (select 4 * (least((select count(*) from rm), (select count(*) from ro)) // 4) as total),
pct(hit_pct) as (values {', '.join(f'({p})' for p in pcts)}),
q as (select hit_pct, k, 1 as is_member from rm, qn, pct where r <= total * hit_pct // 100
      union all select hit_pct, k, 0 from ro, qn, pct where r <= total - total * hit_pct // 100)"""


def mix_confusion(spec: FilterSpec, pcts: tuple[int, ...] = PCTS) -> str:
    return f"""with recursive {query_mix(pcts=pcts)}, {reported_ctes(spec)}
select hit_pct, count(*) as n_queries, count(r.k) as n_reported, sum(is_member)::bigint as n_true,
  count(case when r.k is not null and is_member = 0 then 1 end) as n_false_pos, count(case when r.k is null and is_member = 1 then 1 end) as n_false_neg,
  case when count(*) > sum(is_member) then (count(case when r.k is not null and is_member = 0 then 1 end) * 1000000 // (count(*) - sum(is_member)))::bigint else 0 end as fpp_ppm
from q left join reported r on r.k = q.k group by hit_pct"""
