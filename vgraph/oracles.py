"""DuckDB twins of ``queries``; sampling agrees bit for bit through the portable mix."""

from __future__ import annotations

from .core.mix import mix_sql
from .queries import CACHE, CLUSTERS, K, M, SEED, S, TILE


def d2(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda z: (z[1] - z[2]) * (z[1] - z[2])))"


E = "e as materialized (select vec_id as id, cast(embedding as double[]) as v, label from embeddings)"
R = "round(d2, 6) as d2"


def knn(k: int = K) -> str:
    return f"""{E}, alld as materialized (select a.id as src, b.id as dst, {d2('a.v', 'b.v')} as d2 from e a, e b where a.id <> b.id),
knn as materialized (select src, dst, rank, d2 from (select *, row_number() over (partition by src order by d2, dst) as rank from alld) where rank <= {k})"""


Q = "q as (select id as qid, v as qv from e where id % 100 = 0)"

RANDOM = f"""n as (select count(*) as n from e),
slot as (select e.id as src, t, (e.id + 1 + {mix_sql('e.id', 't', str(SEED))} % (n - 1)) % n as dst from e, n, range(0, {2 * K}) r(t)
  union all select e.id, {2 * K} + t, (e.id + 1 + t) % n from e, n, range(0, {K}) r(t)),
once as (select src, dst, min(t) as t from slot group by 1, 2),
pick as (select src, dst from (select *, row_number() over (partition by src order by t) as r from once) where r <= {K}),
rg as materialized (select src, dst, row_number() over (partition by src order by d2, dst) as rank, d2 from (select p.src, p.dst, {d2('a.v', 'b.v')} as d2 from pick p join e a on a.id = p.src join e b on b.id = p.dst))"""

HALF = f"{E}, {RANDOM}, half as materialized (select *, {mix_sql('7', 'src', 'dst')} % 2 = 0 as fresh from rg)"
SAMPLE = f"sampled as materialized (select src, dst, fresh from (select *, row_number() over (partition by src, fresh order by {mix_sql(str(SEED), '1', 'src', 'dst')}, dst) as r from half) where r <= {S})"
GROUPS = f"""back as (select anchor, member, fresh from (select dst as anchor, src as member, fresh, row_number() over (partition by dst, fresh order by {mix_sql(str(SEED), '1', 'dst', 'src')}, src) as r from sampled) where r <= {S}),
memb as (select anchor, member, min(case when fresh then 0 else 1 end) as part from (select src as anchor, dst as member, fresh from sampled union select anchor, member, fresh from back) group by 1, 2),
grp as materialized (select *, row_number() over (partition by anchor order by part, member) - 1 as pos from memb),
pairs as materialized (select x.anchor, x.member as a, y.member as b, x.pos as apos, y.pos as bpos, {d2('ea.v', 'eb.v')} as d2 from grp x join grp y on x.anchor = y.anchor and x.part = 0 and x.pos < y.pos join e ea on ea.id = x.member join e eb on eb.id = y.member),
offers as (select anchor, a as target, b as partner, bpos as pos, d2 from pairs union all select anchor, b, a, apos, d2 from pairs),
tiled as (select distinct target, partner, d2 from (select *, row_number() over (partition by target, anchor, pos // {TILE} order by d2, partner) as r from offers) where r = 1)"""


def updated(offers: str, base: str) -> str:
    return f"""kth as (select src, max(d2) as kth, count(*) as n from {base} group by 1),
ok as (select distinct o.target as src, o.partner as dst, o.d2 from {offers} o join kth on kth.src = o.target where o.target <> o.partner and (n < {K} or o.d2 < kth) and not exists (select 1 from {base} b where b.src = o.target and b.dst = o.partner)),
allofit as (select src, dst, d2 from {base} union all select src, dst, d2 from ok)
select src, dst, rank, {R} from (select *, row_number() over (partition by src order by d2, dst) as rank from allofit) where rank <= {K}"""


def greedy(conflict: str, cand: str, degree: int) -> str:
    """Greedy in rank order by recursion over ranks: a candidate is kept unless a kept one before it forbids it."""
    return f"""cand as materialized ({cand}),
blk as materialized (select i.src, j.rank as j, list(i.rank) as blockers from (select c.*, e.v from cand c join e on e.id = c.dst) i join (select c.*, e.v from cand c join e on e.id = c.dst) j on i.src = j.src and i.rank < j.rank where {conflict} group by 1, 2),
top as (select max(rank) as top from cand),
fold as (
  select src, 0 as j, cast([] as bigint[]) as kept from (select distinct src from cand)
  union all
  select f.src, f.j + 1, case when c.src is not null and len(f.kept) < {degree} and not list_has_any(f.kept, coalesce(b.blockers, cast([] as bigint[]))) then list_append(f.kept, f.j + 1) else f.kept end
  from fold f left join cand c on c.src = f.src and c.rank = f.j + 1 left join blk b on b.src = f.src and b.j = f.j + 1, top where f.j < top.top),
done as (select src, unnest(kept) as r, unnest(range(1, len(kept) + 1)) as rank from fold, top where j = top.top)
select d.src, c.dst, d.rank, round(c.d2, 6) as d2 from done d join cand c on c.src = d.src and c.rank = d.r"""


def dist_conflict(alpha: float) -> str:
    return f"j.d2 >= {alpha} * {alpha} * {d2('i.v', 'j.v')}"


def angle(pa: str, pb: str, ab: str) -> str:
    return f"(case when {pa} = 0 or {pb} = 0 then 0.0 else degrees(acos(greatest(-1.0, least(1.0, ({pa} + {pb} - {ab}) / (2 * sqrt({pa}) * sqrt({pb})))))) end)"


ONE = "select src, dst, rank, d2 from knn"
TWO = f"""select src, dst, hop, rank, d2 from (select *, row_number() over (partition by src order by d2, dst) as rank from (
  select src, dst, min(hop) as hop, any_value(d2) as d2 from (
    select src, dst, 1 as hop, d2 from knn
    union all
    select f.src, f.dst, 2, a.d2 from (select distinct k1.src, k2.dst from knn k1 join knn k2 on k1.dst = k2.src where k1.src <> k2.dst) f join alld a on a.src = f.src and a.dst = f.dst)
  group by 1, 2)) where rank <= 20"""

DETOUR = """det as (select e.src, e.dst, e.rank, count(t.r) as detours from knn e left join (select a.src, b.dst, greatest(a.rank, {far}) as r from knn a join knn b on {join}) t on t.src = e.src and t.dst = e.dst and t.r < e.rank group by 1, 2, 3)"""
FORWARD = DETOUR.format(far="b.rank", join="a.dst = b.src")
BACKWARD = """det as (select e.src, e.dst, e.rank, count(t.r) as detours from knn e left join (select a.src, b.src as dst, greatest(a.rank, b.rank) as r from knn a join knn b on a.dst = b.dst) t on t.src = e.src and t.dst = e.dst and t.r < e.rank group by 1, 2, 3)"""

DISPERSION = f"""c as materialized (select k.src, k.rank, k.dst, k.d2, e.v from knn k join e on e.id = k.dst),
ang as materialized (select a.src, a.rank as a, b.rank as b, {angle('a.d2', 'b.d2', d2('a.v', 'b.v'))} as x from c a join c b on a.src = b.src),
steps as (
  select distinct src, 1 as n, cast([1] as bigint[]) as kept from knn
  union all
  select src, n + 1, list_append(kept, b) from (
    select s.src, s.n, s.kept, g.b, row_number() over (partition by s.src order by round(sum(g.x), 9) desc, g.b) as r
    from steps s join ang g on g.src = s.src and list_contains(s.kept, g.a) and not list_contains(s.kept, g.b) where s.n < 5 group by 1, 2, 3, 4) where r = 1),
done as (select src, unnest(kept) as r, unnest(range(1, len(kept) + 1)) as rank from steps where n = 5)
select d.src, k.dst, d.rank, round(k.d2, 6) as d2 from done d join knn k on k.src = d.src and k.rank = d.r"""

CENT = f"cent as materialized (select row_number() over (order by {mix_sql(str(SEED), 'id')}, id) - 1 as shard, v as cv from e qualify shard < {CLUSTERS})"


def assigned(m: int = M) -> str:
    return f"{E}, {CENT}, asg as materialized (select shard, id, choice, d2 from (select shard, id, d2, row_number() over (partition by id order by d2, shard) as choice from (select c.shard, e.id, {d2('e.v', 'c.cv')} as d2 from e, cent c)) where choice <= {m})"


ORDER = f"ord as (select i as step, i as load, case when i >= {CACHE} then i - {CACHE} end as evict from range(0, {CLUSTERS}) t(i))"
CG = "cg as materialized (select x.shard as a, y.shard as b, count(*) as w from asg x join asg y on x.id = y.id and x.shard < y.shard group by 1, 2)"
GREEDY = f"""sym as materialized (select a, b, w from cg union all select b, a, w from cg),
walk as (
  select 0 as step, 0 as load, cast(null as bigint) as evict, cast([0] as bigint[]) as res, cast([0] as bigint[]) as done
  union all
  select step + 1, x, e, case when e is null then list_append(res, x) else list_append(list_filter(res, lambda r: r <> e), x) end, list_append(done, x) from (
    select w.step, w.res, w.done, c.shard as x, o.e,
      row_number() over (partition by w.step order by coalesce((select sum(s.w) from sym s where s.a = c.shard and list_contains(w.res, s.b)), 0) - coalesce((select s.w from sym s where s.a = c.shard and s.b = o.e), 0) desc, c.shard, o.e) as r
    from walk w, cent c, (select unnest(range(-1, {CLUSTERS})) as e0) u, lateral (select case when u.e0 >= 0 then u.e0 end as e) o
    where w.step + 1 < {CLUSTERS} and not list_contains(w.done, c.shard) and (case when len(w.res) < {CACHE} then o.e is null else o.e is not null and list_contains(w.res, o.e) end)) where r = 1),
ord as materialized (select step, load, evict from walk)"""
LOG = """visit as (select o.step, a.id, lag(o.step) over (partition by a.id order by o.step) as before from asg a join ord o on o.load = a.shard),
log as (select step, id, case when before is null then 'first' when exists (select 1 from asg a join ord g on g.evict = a.shard where a.id = v.id and g.step > v.before and g.step <= v.step) then 'miss' else 'hit' end as outcome from visit v)"""
RATIO = "select count(*) filter (where outcome = 'first') as first, count(*) filter (where outcome = 'hit') as hits, count(*) filter (where outcome = 'miss') as misses, round(count(*) filter (where outcome = 'hit') / nullif(count(*) filter (where outcome <> 'first'), 0), 6) as ratio_revisits, round(count(*) filter (where outcome = 'hit') / nullif(count(*), 0), 6) as ratio_all from log"
LOCALS = f"loc as materialized (select src, dst, d2 from (select x.shard, x.id as src, y.id as dst, {d2('a.v', 'b.v')} as d2, row_number() over (partition by x.shard, x.id order by {d2('a.v', 'b.v')}, y.id) as r from asg x join asg y on x.shard = y.shard and x.id <> y.id join e a on a.id = x.id join e b on b.id = y.id) where r <= 8)"
MERGED = f"{assigned()}, {LOCALS} select src, dst, rank, {R} from (select *, row_number() over (partition by src order by d2, dst) as rank from (select src, dst, min(d2) as d2 from loc group by 1, 2)) where rank <= 8"

STRICT = f"with recursive {knn()}, {greedy(dist_conflict(1.0), ONE, 50)}"

ORACLES = {
    "exact_knn": f"with {knn()} select src, dst, rank, {R} from knn",
    "exact_search_queries": f"with {E}, {Q} select qid, id, rank, {R} from (select *, row_number() over (partition by qid order by d2, id) as rank from (select qid, e.id, {d2('qv', 'v')} as d2 from q, e where qid <> e.id)) where rank <= {K}",
    "range_search_queries": f"with {E}, {Q} select qid, id, {R} from (select qid, e.id, {d2('qv', 'v')} as d2 from q, e) where d2 <= 1.2 * 1.2",
    "filtered_search_label": f"with {E}, {Q} select qid, id, rank, {R} from (select *, row_number() over (partition by qid order by d2, id) as rank from (select qid, e.id, {d2('qv', 'v')} as d2 from q, e where label = 3)) where rank <= {K}",
    "metric_variants": f"with {E}, p as (select b.id, a.v as x, b.v as y from e a join e b on b.id = a.id + 1 where a.id % 100 = 0), n as (select id, {d2('x', 'y')} as d2, list_sum(list_transform(list_zip(x, y), lambda z: z[1] * z[2])) as dot, sqrt(list_sum(list_transform(x, lambda z: z * z))) * sqrt(list_sum(list_transform(y, lambda z: z * z))) as size from p) select id, round(sqrt(d2), 6) as l2, round(1 - dot / nullif(size, 0), 6) as cosine, round(-dot, 6) as inner from n",
    "distance_matrix_stats": f"with {knn()} select rank, count(*) as n, round(avg(d2), 6) as mean_d2, round(min(d2), 6) as min_d2, round(max(d2), 6) as max_d2 from knn group by 1",
    "random_graph": f"with {E}, {RANDOM} select src, dst, rank, {R} from rg",
    "random_graph_recall": f"with {knn()}, {RANDOM} select (select count(*) from e) as queries, round((select count(*) from rg join knn using (src, dst)) / cast({K} as double) / (select count(*) from e), 6) as recall",
    "reverse_graph": f"with {knn()} select src, dst from (select dst as src, src as dst, row_number() over (partition by dst order by {mix_sql(str(SEED), 'dst', 'src')}, src) as r from knn) where r <= 8",
    "merge_rank": f"with {knn()} select src, dst, rank, {R} from knn",
    "sample_fresh_old": f"with {HALF}, {SAMPLE} select src, case when fresh then 'fresh' else 'old' end as part, dst from sampled",
    "local_join_all": f"with {HALF}, {SAMPLE}, {GROUPS} select distinct target, partner, {R} from offers",
    "local_join_tile": f"with {HALF}, {SAMPLE}, {GROUPS} select target, partner, {R} from tiled",
    "local_join_single": f"with {HALF}, {SAMPLE}, {GROUPS} select target, partner, {R} from (select *, row_number() over (partition by target order by d2, partner) as r from offers) where r = 1",
    "local_join_one_iter": f"with {HALF}, {SAMPLE}, {GROUPS}, {updated('tiled', 'half')}",
    "refine_one_iter": f"with {HALF}, cnd as (select distinct x.src as target, y.dst as partner from half x join half y on x.rank <= {M} and y.src = x.dst where x.src <> y.dst), off as (select target, partner, {d2('a.v', 'b.v')} as d2 from cnd join e a on a.id = target join e b on b.id = partner), {updated('off', 'half')}",
    "collect_1hop": f"with {knn()} select src, dst, 1 as hop, rank, {R} from knn where rank <= 8",
    "collect_2hop": f"with {knn()} select src, dst, hop, rank, {R} from ({TWO})",
    "prune_strict": STRICT,
    "prune_wavefront_eq": STRICT,
    "prune_serial_eq": STRICT,
    "prune_relaxed": f"with recursive {knn()}, {greedy(dist_conflict(1.2), ONE, 6)}",
    "prune_custom": f"with recursive {knn()}, {greedy('2 * ' + d2('i.v', 'j.v') + ' <= j.d2', ONE, 50)}",
    "prune_angle": f"with recursive {knn()}, {greedy(angle('i.d2', 'j.d2', d2('i.v', 'j.v')) + ' <= 60.0', TWO, 50)}",
    "prune_dispersion": f"with recursive {knn()}, {DISPERSION}",
    "prune_dispersion_kernel": f"with recursive {knn()}, {DISPERSION}",
    "prune_detour": f"with {knn()}, {FORWARD} select src, dst, place as rank, detours from (select *, row_number() over (partition by src order by detours, rank) as place from det) where place <= 5",
    "detour_counts": f"with {knn()}, {FORWARD} select src, dst, rank, detours from det",
    "detour_counts_backward": f"with {knn()}, {BACKWARD} select src, dst, rank, detours from det",
    "detour_work_unbalanced": f"with {knn()} select 'per_candidate' as kernel, count(*) as units, max(rank - 1) as max_scans, round(avg(rank - 1), 6) as mean_scans, sum(rank - 1) as total_scans from knn",
    "detour_work_paired": f"with {knn()}, u as (select src, least(rank, {K} + 2 - rank) as unit, sum(rank - 1) as scans from knn where rank >= 2 group by 1, 2) select 'paired' as kernel, count(*) as units, max(scans) as max_scans, round(avg(scans), 6) as mean_scans, sum(scans) as total_scans from u",
    "store_filled": f"with recursive {knn()}, kept as materialized (with recursive {greedy(dist_conflict(1.0), ONE, 6)}), tops as (select src, dst, rank, d2, 0 as late from kept union all select k.src, k.dst, k.rank, round(k.d2, 6), 1 from knn k where not exists (select 1 from kept z where z.src = k.src and z.dst = k.dst)) select src, dst, place as rank, d2 from (select *, row_number() over (partition by src order by late, rank) as place from tops) where place <= 6",
    "store_padded": f"with recursive {knn()}, kept as materialized (with recursive {greedy(dist_conflict(1.0), ONE, 8)}) select src, array_to_string(list_concat(list(dst order by rank), list_transform(range(0, 8 - count(*)), lambda x: -1)), ',') as nbrs, count(*) as deg from kept group by 1",
    "entry_point": f"with {E}, mean as (select list(x order by p) as m from (select p, avg(x) as x from (select unnest(range(len(v))) as p, unnest(v) as x from e) group by 1)) select id, {R} from (select id, {d2('v', 'm')} as d2 from e, mean) order by d2, id limit 1",
    "graph_stats": f"with {knn()}, deg as (select e.id, count(k.dst) as deg from e left join knn k on k.src = e.id group by 1), ind as (select dst, count(*) as n from knn group by 1) select (select count(*) from deg) as nodes, (select sum(deg) from deg) as edges, (select min(deg) from deg) as min_deg, (select max(deg) from deg) as max_deg, (select round(avg(deg), 6) from deg) as mean_deg, (select max(n) from ind) as max_in, (select round(avg(d2), 6) from knn) as mean_d2",
    "in_degree": f"with {knn()} select e.id, count(k.src) as n_in from e left join knn k on k.dst = e.id group by 1",
    "reachability": f"with recursive {knn()}, mean as (select list(x order by p) as m from (select p, avg(x) as x from (select unnest(range(len(v))) as p, unnest(v) as x from e) group by 1)), ent as (select id from e, mean order by {d2('v', 'm')}, id limit 1), walk as (select id, 0 as hop from ent union select k.dst, w.hop + 1 from walk w join knn k on k.src = w.id where w.hop < 12) select hop, count(*) as n from (select id, min(hop) as hop from walk group by 1) group by 1",
    "weak_components": f"with recursive {knn(3)}, und as materialized (select src as a, dst as b from knn union select dst, src from knn), walk as (select id, id as comp from e union select u.b, w.comp from walk w join und u on u.a = w.id) select comp, count(*) as n from (select id, min(comp) as comp from walk group by 1) group by 1",
    "footprint": f"with {E} select count(*) as n, max(len(v)) as dim, count(*) * max(len(v)) * 4 as vector_bytes, count(*) * 32 * 4 as list_bytes from e",
    "assign_overlapping": f"with {assigned()} select shard, id, choice, {R} from asg",
    "kmeans_assign": f"with {assigned(1)} select shard, id, {R} from asg",
    "kmeans_step": f"with {assigned(1)}, mv as (select shard, p, avg(x) as x from (select a.shard, unnest(range(len(e.v))) as p, unnest(e.v) as x from asg a join e using (id)) group by 1, 2), old as (select shard, unnest(range(len(cv))) as p, unnest(cv) as x from cent) select old.shard, old.p, round(coalesce(mv.x, old.x), 6) as x from old left join mv using (shard, p)",
    "cluster_overlap_graph": f"with {assigned()}, {CG} select a, b, w from cg",
    "shard_size_table": f"with {assigned()} select shard, count(*) as n from asg group by 1",
    "shard_overlap_stats": f"with {assigned()}, sz as (select count(*) as n from asg group by shard) select sum(n) as rows, (select count(*) from e) as nodes, round(sum(n) / cast((select count(*) from e) as double), 6) as replication, max(n) as largest, min(n) as smallest, round(avg(n), 6) as mean_size from sz",
    "dispatch_sequential": f"with {ORDER} select step, load, evict from ord",
    "dispatch_greedy": f"with recursive {assigned()}, {CG}, {GREEDY} select step, load, evict from ord",
    "cache_replay_sequential": f"with {assigned()}, {ORDER}, {LOG} {RATIO}",
    "cache_replay_greedy": f"with recursive {assigned()}, {CG}, {GREEDY}, {LOG} {RATIO}",
    "io_operations": f"with {assigned()}, {ORDER}, {LOG} select 2 * count(*) filter (where outcome = 'miss') as cached_io, count(*) filter (where outcome = 'first') as flush_io, 3 * count(*) filter (where outcome = 'first') as baseline_per_node, 2 * count(*) + count(*) filter (where outcome = 'first') as baseline_exact from log",
    "window_objective": f"with {assigned()}, {CG} select coalesce(sum(w), 0) as objective from cg where b - a < {CACHE}",
    "merge_of_locals": f"with {MERGED}",
    "cache_merge_graph": f"with {MERGED}",
    "cache_merge_io": f"with {assigned()}, {ORDER}, {LOG} select count(*) filter (where outcome = 'miss') as reads, count(*) filter (where outcome <> 'hit') as writes from log",
    "merge_of_locals_ordered": f"with {MERGED}",
    "doc_vectors": "with t as (select doc_id as id, list_transform(string_split(text, ''), lambda c: unicode(c)) as u from documents where length(text) >= 3), g as (select id, (((u[i] * 31 + u[i + 1]) * 31 + u[i + 2]) % 1000003) % 96 as p from t, unnest(range(1, len(u) - 1)) r(i)), c as (select id, p, count(*) as n from g group by 1, 2) select id, cast(p as integer) as p, round(n / sqrt(sum(n * n) over (partition by id)), 6) as x from c",
    "line_vectors": "select row_number() over (order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice, l_quantity) - 1 as id, round(l_quantity / 50, 6) as x0, round(l_extendedprice / (select max(l_extendedprice) from lineitem), 6) as x1, round(l_discount * 10, 6) as x2, round(l_tax * 12.5, 6) as x3 from lineitem",
    "event_vectors": "select user_id as id, " + ", ".join(f"round(cast(count(*) filter (where event_type = '{k}') as double), 4) as x{i}" for i, k in enumerate(("view", "click", "purchase", "signup", "error"))) + ", round(avg(value), 4) as x5 from events group by 1",
}

ORACLES |= {
    "w_sampling_toy": f"""with {E}, {RANDOM}, one as (select src as anchor, dst as fresh from rg where rank = 1 and src % 100 = 0),
offered as (select anchor, fresh, 'shared' as sampling, dst as member from one join rg on src = anchor
  union select anchor, fresh, 'per_node', dst from one join rg on src = fresh
  union select anchor, fresh, 'per_node', b.dst from one join rg a on a.src = fresh join rg b on b.src = a.dst),
near as (select anchor, sampling, member, row_number() over (partition by anchor, sampling order by {d2('x.v', 'y.v')}, member) - 1 as place
  from offered join e x on x.id = fresh join e y on y.id = member where member <> fresh)
select anchor, sampling, cast(place as integer) as place, member from near where place < 2""",
    "w_rebuild_trigger": "with x as (select cast(ts as date) as day, user_id % 8 as user_shard, count(distinct user_id) as changed from events group by 1, 2), n as (select user_id % 8 as user_shard, count(distinct user_id) as n from events group by 1) select day, user_shard, changed, changed > 0.8 * n as rebuild from x join n using (user_shard)",
    "churn_daily": "select cast(ts as date) as day, count(*) filter (where event_type <> 'error') as upserts, count(*) filter (where event_type = 'error') as deletes from events group by 1",
}
