"""The registered queries in plain SQL, written independently of the operators, for comparison on the same tables."""

from __future__ import annotations

SECOND, CAP, WIDTH, PRIME = 10_000_000, 3, 257, 2147483647
FACTORS = ((1103515245, 12345), (1664525013, 1013904223), (1597334677, 715136305), (950706376, 374761393))
ORDER = "(src * 7919 + dst * 104729) % 1000003, src, dst"

PLANTED = f"""
raw as (select distinct cast(o_custkey as bigint) as src, cast(l_partkey as bigint) + {SECOND} as dst
        from orders join lineitem on o_orderkey = l_orderkey
        where o_custkey % 15 = l_partkey % 15 or (o_custkey * 7919 + l_partkey * 104729) % 100 < 2),
e as (select row_number() over (order by {ORDER}) as seq, src, dst from raw)"""
DEGREES = "deg as (select node, count(*) as deg from (select src as node from e union all select dst from e) group by node)"
TRUTH = f"truth as (select node, (case when node >= {SECOND} then node - {SECOND} else node end) % 15 as community from deg)"
SIZES = "sizes as (select community, cast(sum(deg) as bigint) as size, count(*) as n_nodes from truth join deg using (node) group by community)"
TRUE = f"{PLANTED}, {DEGREES}, {TRUTH}"


def found(e: str = "e", cap: int = CAP, admit: str = "le", tie: str = "source", p: str = "", labels: str | None = None, offset: str | None = None) -> str:
    """CTEs {p}adm, {p}ev, {p}ptr, {p}label(node, community): one pass of the detector over the edges in e."""
    limit = cap if admit == "le" else cap - 1
    plus = f" + coalesce({offset}.deg, 0)" if offset else ""
    join = f" left join {offset} on {offset}.node = h.node" if offset else ""
    joins = {"source": "ds <= dd", "hold": "ds < dd", "lower_id": "(ds < dd or (ds = dd and src > dst))"}[tie]
    where = " where ds <> dd" if tie == "hold" else ""
    start = f"coalesce((select community from {labels} l where l.node = winner), winner)" if labels else "winner"
    own = f"coalesce(l.community, n.node)" if labels else "n.node"  # noqa: F541
    own_join = f" left join {labels} l on l.node = n.node" if labels else ""
    return f"""
{p}half as (select seq, src as node, 0 as side from {e} union all select seq, dst, 1 from {e}),
{p}rk as (select h.seq, h.node, h.side, row_number() over (partition by h.node order by h.seq){plus} as deg from {p}half h{join}),
{p}adm as (select a.seq, a.node as src, b.node as dst, a.deg as ds, b.deg as dd from {p}rk a join {p}rk b on a.seq = b.seq and a.side = 0 and b.side = 1
           where a.deg <= {limit} and b.deg <= {limit}),
{p}ev as (select seq, case when {joins} then src else dst end as loser, case when {joins} then dst else src end as winner from {p}adm{where}),
{p}ptr as materialized (select v.seq, v.loser, v.winner, x.seq as ptr from {p}ev v asof left join {p}ev x on v.winner = x.loser and v.seq > x.seq),
{p}chase as (select seq, loser, ptr, case when ptr is null then {start} end as label from {p}ptr
             union all
             select c.seq, c.loser, q.ptr, case when q.ptr is null then {start} end from {p}chase c join {p}ptr q on c.ptr = q.seq where c.ptr is not null),
{p}last as (select loser as node, arg_max(label, seq) as label from {p}chase where label is not null group by loser),
{p}label as (select n.node, coalesce(t.label, {own}) as community from (select src as node from {e} union select dst from {e}) n left join {p}last t on t.node = n.node{own_join})"""


def contracted(e: str, label: str) -> str:
    return f"select x.seq, a.community as src, b.community as dst from {e} x join {label} a on x.src = a.node join {label} b on x.dst = b.node where a.community <> b.community"


TWO = f"{PLANTED}, {found(cap=2, p='a')}, e2 as ({contracted('e', 'alabel')}), {found('e2', 4, p='b')}, two as (select x.node, coalesce(y.community, x.community) as community from alabel x left join blabel y on x.community = y.node)"
ONE = f"{PLANTED}, {DEGREES}, {found()}"


def split(label: str, e: str = "e", w: str = "1") -> str:
    return f"""
ab as (select a.community as cs, b.community as cd, {w} as w from {e} x join {label} a on x.src = a.node join {label} b on x.dst = b.node),
parts as (select community, cast(sum(i) as bigint) as "inner", cast(sum(c) as bigint) as "cross", cast(sum(2 * i + c) as bigint) as volume
          from (select cs as community, w as i, 0 as c from ab where cs = cd union all select cs, 0, w from ab where cs <> cd union all select cd, 0, w from ab where cs <> cd) group by community)"""


Q = """round(2.0 * sum("inner") / sum(volume) - sum(cast(volume as double) * volume) / (cast(sum(volume) as double) * sum(volume)), 6) as q from parts"""
SUPER = "select least(cs, cd) as src, greatest(cs, cd) as dst, count(*) as w from ab where cs <> cd group by 1, 2"


def cell(x: str, i: int, width: int = WIDTH) -> str:
    a, b = FACTORS[i]
    return f"(({a} * ({x} % {PRIME}) + {b}) % {PRIME}) % {width}"


def matrix(source: str, key: str, weight: str, depth: int = 4, width: int = WIDTH) -> str:
    rows = " union all ".join(f"select {i + 1} as row_no, {cell(key, i, width)} as cell, {weight} as w from {source}" for i in range(depth))
    return f"sk as (select row_no, cell, cast(sum(w) as bigint) as cnt from ({rows}) group by row_no, cell)"


def estimate(source: str, key: str, depth: int = 4, width: int = WIDTH) -> str:
    rows = " union all ".join(f"select {key}, {i + 1} as row_no, {cell(key, i, width)} as cell from (select distinct {key} from {source})" for i in range(depth))
    return f"est as (select {key}, min(cnt) as est from ({rows}) k join sk using (row_no, cell) group by {key})"


_H = [f"(({a} * (node % {PRIME}) + {b}) % {PRIME}) / 2147483647.0" for a, b in FACTORS[:2]]
START = f"""pos as (select node, sqrt({_H[0]}) * 100 * cos({_H[1]} * 2 * pi()) as x, sqrt({_H[0]}) * 100 * sin({_H[1]} * 2 * pi()) as y, mass from spots)"""
PLACED = f"{TRUE}, {SIZES}, spots as (select community as node, cast(size as double) as mass from sizes), {START}, {split('truth')}, se as ({SUPER})"
EVERY = f"{TRUE}, spots as (select node, 1.0 as mass from deg), {START}"
PULL = """pull as (select node, sum(fx) as fx, sum(fy) as fy from (
    select src as node, {f} * (b.x - a.x) as fx, {f} * (b.y - a.y) as fy from se join pos a on se.src = a.node join pos b on se.dst = b.node
    union all select dst, -{f} * (b.x - a.x), -{f} * (b.y - a.y) from se join pos a on se.src = a.node join pos b on se.dst = b.node) group by node)"""
_D = "sqrt((b.x - a.x) * (b.x - a.x) + (b.y - a.y) * (b.y - a.y))"
PUSH = """push as (select a.node, sum(80.0 * {m} / d2 * dx) as fx, sum(80.0 * {m} / d2 * dy) as fy
  from (select a.node, a.mass as ma, b.mass as mb, a.x - b.x as dx, a.y - b.y as dy, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) as d2 from pos a join pos b on a.node <> b.node) a group by a.node)"""
GRAVITY = "grav as (select node, -mass * x / sqrt(x * x + y * y) as fx, -mass * y / sqrt(x * x + y * y) as fy from pos)"
FORCES = f"{PLACED}, {PULL.format(f='w')}, {PUSH.format(m='ma * mb')}, {GRAVITY}, total as (select node, sum(fx) as fx, sum(fy) as fy from (select * from pull union all select * from push union all select * from grav) group by node)"
XY = "node, round({0}, 3) as {0}, round({1}, 3) as {1}"

_MANY = f"{ONE}, sizes as (select community, cast(sum(deg) as bigint) as size from label join deg using (node) group by community)"
_NAMES = "names(band, name) as (values (0, 'brown'), (1, 'light purple'), (2, 'purple'), (3, 'light orange'), (4, 'orange'), (5, 'light red'), (6, 'red'), (7, 'light green'), (8, 'green'), (9, 'light blue'), (10, 'blue'))"
_RUN = "run as (select community, size, sum(size) over (order by size, community) <= 0.5 * (select sum(size) from sizes) as tail from sizes)"


def bands(rule: str) -> str:
    return f"with recursive {_MANY}, {_RUN}, {_NAMES}, b as (select community, size, case when tail then 0 else {rule} end as band from run) select community, size, cast(b.band as int) as band, name from b join names on b.band = names.band"


_CONT = f"{ONE}, {TRUTH}, cont as (select label.community as c, truth.community as t, count(*) as n from label join truth using (node) group by 1, 2)"
_TYPED = f"{TRUE}, typed as (select community, deg, case when node >= {SECOND} then 'part' else 'customer' end as side from truth join deg using (node))"
_EVK = f"select cast(ts as timestamp) as ts, user_id as src, cast(json_extract_string(props, '$.k') as bigint) + {SECOND} as dst from events where json_extract_string(props, '$.k') is not null"
_T = "select l_suppkey as src, l_partkey as dst from lineitem where l_quantity > 25"
_U = "select l_suppkey as src, l_partkey as dst from lineitem where l_quantity <= 25"
_NEXT = "nx as (select user_id as a, lead(user_id) over (order by ts, event_id) as b from events)"
_LINES = """ln as (select distinct doc_id, trim(l) as line from (select doc_id, unnest(string_split(text, chr(10))) as l from documents) where length(trim(l)) >= 20),
few as (select line from ln group by line having count(*) between 2 and 50), sl as (select ln.* from ln join few using (line))"""
_TRADE = """trade as (select cast(c_nationkey as bigint) as src, cast(s_nationkey as bigint) as dst, count(*) as w from orders join lineitem on o_orderkey = l_orderkey
join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2)"""
_UND = f"{_TRADE}, und as (select least(src, dst) as src, greatest(src, dst) as dst, cast(sum(w) as bigint) as w from trade group by 1, 2)"


def traced(steps: int) -> str:
    """CTEs up to trace(i, m, d): largest move and diameter of each step of the planted groups' layout."""
    out = [PLACED, "p0 as (select node, x, y, mass, 0.0 as fx, 0.0 as fy from pos)", "g0 as (select 1.0 as g)"]
    for i in range(1, steps + 1):
        p = f"p{i - 1}"
        speed = "1.0" if i == 1 else "case when swing > 1e-9 then least(traction / swing, 1.5 * g) else 1.5 * g end"
        out += [
            f"drawn{i} as (select src, dst, w * (b.x - a.x) as fx, w * (b.y - a.y) as fy from se join {p} a on src = a.node join {p} b on dst = b.node)",
            f"apart{i} as (select a.node, 80.0 * a.mass * b.mass * (a.x - b.x) / ((a.x - b.x) ** 2 + (a.y - b.y) ** 2) as fx, 80.0 * a.mass * b.mass * (a.y - b.y) / ((a.x - b.x) ** 2 + (a.y - b.y) ** 2) as fy from {p} a join {p} b on a.node <> b.node where (a.x - b.x) ** 2 + (a.y - b.y) ** 2 > 1e-9)",
            f"held{i} as (select node, -mass * x / sqrt(x * x + y * y) as fx, -mass * y / sqrt(x * x + y * y) as fy from {p} where sqrt(x * x + y * y) > 1e-9)",
            f"f{i} as (select node, sum(fx) as fx, sum(fy) as fy from (select src as node, fx, fy from drawn{i} union all select dst, -fx, -fy from drawn{i} union all select * from apart{i} union all select * from held{i}) group by node)",
            f"o{i} as (select p.node, p.x, p.y, p.mass, coalesce(f.fx, 0) as fx, coalesce(f.fy, 0) as fy, sqrt((coalesce(f.fx, 0) - p.fx) ** 2 + (coalesce(f.fy, 0) - p.fy) ** 2) as sw, sqrt((coalesce(f.fx, 0) + p.fx) ** 2 + (coalesce(f.fy, 0) + p.fy) ** 2) / 2 as tr from {p} p left join f{i} f using (node))",
            f"g{i} as (select {speed} as g from g{i - 1}, (select sum(mass * sw) as swing, sum(mass * tr) as traction from o{i}))",
            f"p{i} as (select node, x + g / (1 + g * sqrt(sw)) * fx as x, y + g / (1 + g * sqrt(sw)) * fy as y, mass, fx, fy from o{i}, g{i})",
            f"m{i} as (select {i} as i, max(sqrt((a.x - b.x) ** 2 + (a.y - b.y) ** 2)) as m, sqrt((max(a.x) - min(a.x)) ** 2 + (max(a.y) - min(a.y)) ** 2) as d from p{i} a join {p} b using (node))",
        ]
    return ", ".join([*out, "trace as (" + " union all ".join(f"select * from m{i}" for i in range(1, steps + 1)) + ")"])


def plain(ctes: str, body: str) -> str:
    return f"with recursive {ctes} {body}"


ORACLES: dict[str, str] = {
    "canonical_edges": plain(_NEXT, "select least(a, b) as src, greatest(a, b) as dst, count(*) as w from nx where b is not null and a <> b group by 1, 2"),
    "arrival_rank": plain(PLANTED, "select * from e"),
    "degrees": plain(f"{PLANTED}, {DEGREES}", "select * from deg"),
    "degrees_directed": plain(_TRADE, "select node, cast(sum(o) as bigint) as deg_out, cast(sum(1 - o) as bigint) as deg_in from (select src as node, 1 as o from trade union all select dst, 0 from trade) group by node"),
    "degrees_weighted": plain(_UND, "select node, cast(sum(w) as bigint) as deg from (select src as node, w from und union all select dst, w from und) group by node"),
    "degree_histogram": plain(f"{PLANTED}, {DEGREES}", "select deg, count(*) as n from deg group by deg"),
    "base_cap_mode": plain(f"{PLANTED}, {DEGREES}", "select deg as cap from deg group by deg order by count(*) desc, deg limit 1"),
    "base_cap_average": plain(f"{PLANTED}, {DEGREES}", "select cast(floor(sum(deg) / count(*)) as bigint) as cap from deg"),
    "admitted_edges": plain(f"{PLANTED}, {found()}", "select seq, src, dst, ds as src_deg, dd as dst_deg from adm"),
    "copy_events": plain(f"{PLANTED}, {found()}", "select * from ev"),
    "event_pointers": plain(f"{PLANTED}, {found()}", "select * from ptr"),
    "assignment_le_source": plain(f"{PLANTED}, {found()}", "select * from label"),
    "assignment_le_hold": plain(f"{PLANTED}, {found(tie='hold')}", "select * from label"),
    "assignment_lt_source": plain(f"{PLANTED}, {found(admit='lt')}", "select * from label"),
    "assignment_lower_id": plain(f"{PLANTED}, {found(tie='lower_id')}", "select * from label"),
    "assignment": plain(f"raw as (select distinct l_orderkey as src, l_partkey + 1000000000 as dst from lineitem), e as (select row_number() over (order by {ORDER}) as seq, src, dst from raw), {found(cap=4)}", "select * from label"),
    "assignment_two_rounds": plain(TWO, "select * from two"),
    "assignment_labels_carried": plain(f"{PLANTED}, {DEGREES}, {found(cap=2, p='a')}, {found(cap=4, p='b', labels='alabel', offset='deg')}", "select * from blabel"),
    "bulk_assignment": plain(f"""{PLANTED}, {DEGREES}, {found()}, both_ as (select src, dst from adm union select dst, src from adm),
        up as (select b.src as node, arg_max(b.dst, (y.deg, -b.dst)) as up from both_ b join deg x on b.src = x.node join deg y on b.dst = y.node where y.deg > x.deg or (y.deg = x.deg and b.dst < b.src) group by b.src),
        climb as (select node, node as top from deg union all select c.node, u.up from climb c join up u on c.top = u.node)""", "select node, top as community from climb where not exists (select 1 from up where up.node = climb.top)"),
    "loop_assignment": plain(f"{PLANTED}, {found()}", "select * from label"),
    "loop_stalled": plain(f"{PLANTED}, {DEGREES}", "select node, node as community from deg"),
    "hierarchy_paths": plain(TWO, "select x.node, [x.community, coalesce(y.community, x.community)] as path from alabel x left join blabel y on x.community = y.node"),
    "members": plain(TWO, "select node from two where community = (select community from two group by community order by count(*) desc, community limit 1)"),
    "community_sizes_exact": plain(f"{TRUE}, {SIZES}", "select * from sizes"),
    "sketch_cells": plain(f"{PLANTED}, {DEGREES}, {matrix('deg', 'node', 'deg')}", "select * from sk"),
    "sketch_sequential": plain(f"{PLANTED}, {DEGREES}, {matrix('deg', 'node', 'deg')}", "select * from sk"),
    "sketch_merge": plain(f"{PLANTED}, {DEGREES}, {matrix('deg', 'node', 'deg')}", "select * from sk"),
    "sketch_sizes": plain(f"{TRUE}, wt as (select community, deg from truth join deg using (node)), {matrix('wt', 'community', 'deg')}, {estimate('wt', 'community')}", "select community, est as size from est"),
    "sketch_error": plain(f"{PLANTED}, {DEGREES}, {matrix('deg', 'node', 'deg')}, {estimate('deg', 'node')}", "select round(avg(est - deg), 6) as mean_error, max(est - deg) as max_error, min(est - deg) as min_error, round(quantile_cont(est - deg, 0.95), 6) as p95_error from est join deg using (node)"),
    "sketch_column_min": plain(f"{PLANTED}, {DEGREES}, {matrix('deg', 'node', 'deg')}", "select cell, case when count(*) < 4 then 0 else min(cnt) end as least from sk group by cell"),
    "hash_table_sizes": plain(f"{TRUE}, wt as (select community, deg from truth join deg using (node)), {matrix('wt', 'community', 'deg', 1, 17)}, {estimate('wt', 'community', 1, 17)}", "select community, est as size from est"),
    "sketch_memory": plain(f"{PLANTED}, {DEGREES}", f"select {4 * WIDTH} as cells, {4 * WIDTH * 8} as bytes, round(sum(deg) / {WIDTH}.0, 6) as load from deg"),
    "supernodes": plain(f"{TRUE}, {SIZES}", "select community, size, n_nodes from sizes"),
    "superedges": plain(f"{TRUE}, {split('truth')}", SUPER),
    "supergraph_counts": plain(f"{ONE}, {split('label')}", f"select (select count(distinct community) from label) as sn, (select count(*) from ({SUPER})) as se"),
    "compression": plain(f"{ONE}, {split('label')}", f"select round((select count(*) from label) / (select count(distinct community) from label), 6) as node_ratio, round((select count(*) from e) / (select count(*) from ({SUPER})), 6) as edge_ratio"),
    "edge_split": plain(f"{TRUE}, {split('truth')}", "select * from parts"),
    "modularity": plain(f"{TRUE}, {split('truth')}", f"select {Q}"),
    "modularity_found": plain(f"{ONE}, {split('label')}", f"select {Q}"),
    "modularity_pairs": plain(f"{TRUE}, {split('truth')}", f"select {Q}"),
    "modularity_weighted": plain(f"{_UND}, nat as (select cast(n_nationkey as bigint) as node, cast(n_regionkey as bigint) as community from nation), {split('nat', 'und', 'x.w')}", f"select {Q}"),
    "intra_probability": plain(f"{TRUE}, {split('truth')}", 'select community, round(' + " * ".join(f'(greatest("inner" - {k}, 0) / ("inner" + "cross" - {k}))' for k in range(5)) + ", 6) as p from parts"),
    "phi": plain(f"{TRUE}, {split('truth')}", 'select community, round("cross" / (2 * "inner" + "cross" - 2), 6) as phi from parts'),
    "purity": plain(_CONT, "select round(sum(top) / sum(n), 6) as purity from (select max(n) as top, sum(n) as n from cont group by c)"),
    "nmi": plain(f"{_CONT}, p as (select c, t, n / (select sum(n) from cont) as p from cont), pc as (select c, sum(p) as pc from p group by c), pt as (select t, sum(p) as pt from p group by t)",
                 "select round(2 * (select sum(p * ln(p / (pc * pt))) from p join pc using (c) join pt using (t)) / ((select -sum(pc * ln(pc)) from pc) + (select -sum(pt * ln(pt)) from pt)), 6) as nmi"),
    "pair_scores": plain(f"{_CONT}, k as (select (select sum(n * (n - 1) / 2) from cont) as both_, (select sum(n * (n - 1) / 2) from (select sum(n) as n from cont group by c)) as f, (select sum(n * (n - 1) / 2) from (select sum(n) as n from cont group by t)) as t)",
                         "select round(both_ / f, 6) as pair_precision, round(both_ / t, 6) as pair_recall, round(2 * both_ / (f + t), 6) as pair_f1 from k"),
    "assignment_agreement": plain(f"{PLANTED}, {found(p='a')}, {found(tie='hold', p='b')}", "select count(*) filter (where a.community = b.community) as same, count(*) filter (where a.community <> b.community) as different, count(*) filter (where a.node is null or b.node is null) as missing from alabel a full join blabel b on a.node = b.node"),
    "size_profile": plain(_MANY, "select cast(floor(log2(size)) as bigint) as bucket, count(*) as n, cast(sum(size) as bigint) as total from sizes group by 1"),
    "large_blobs": plain(f"{TRUE}, {SIZES}", "select count(*) as blobs from sizes where size >= 0.05 * (select sum(size) from sizes)"),
    "layout_init": plain(PLACED, "select node, round(x, 3) as x, round(y, 3) as y, round(mass, 3) as mass from pos"),
    "gravity_step": plain(f"{PLACED}, {GRAVITY}", f"select {XY.format('fx', 'fy')} from grav"),
    "gravity_strong_step": plain(PLACED, "select node, round(-mass * x, 3) as fx, round(-mass * y, 3) as fy from pos"),
    "attraction_step": plain(f"{PLACED}, {PULL.format(f='w')}", f"select {XY.format('fx', 'fy')} from pull"),
    "attraction_unit_step": plain(f"{PLACED}, {PULL.format(f='w / ' + _D)}", f"select {XY.format('fx', 'fy')} from pull"),
    "attraction_log_step": plain(f"{PLACED}, {PULL.format(f='w * ln(1 + ' + _D + ') / ' + _D)}", f"select {XY.format('fx', 'fy')} from pull"),
    "repulsion_exact_step": plain(f"{PLACED}, {PUSH.format(m='1')}", f"select {XY.format('fx', 'fy')} from push"),
    "repulsion_weighted_step": plain(f"{PLACED}, {PUSH.format(m='ma * mb')}", f"select {XY.format('fx', 'fy')} from push"),
    "repulsion_opened_exact": plain(f"{PLACED}, {PUSH.format(m='ma * mb')}", f"select {XY.format('fx', 'fy')} from push"),
    "speeds_step": plain(FORCES, "select node, round(sqrt(fx * fx + fy * fy), 3) as swing, round(1 / (1 + sqrt(sqrt(fx * fx + fy * fy))), 6) as speed from total"),
    "speeds_paper_step": plain(FORCES, "select node, round(sqrt(fx * fx + fy * fy), 3) as swing, round(1 / (1 + sqrt(1 + sqrt(fx * fx + fy * fy))), 6) as speed from total"),
    "move_step": plain(FORCES, "select node, round(x + fx / (1 + sqrt(sqrt(fx * fx + fy * fy))), 3) as x, round(y + fy / (1 + sqrt(sqrt(fx * fx + fy * fy))), 3) as y from total join pos using (node)"),
    "extent": plain(EVERY, "select community, count(*) as n_nodes, round(sqrt(var_pop(x) + var_pop(y)), 6) as rms_radius, count(distinct (floor(x / 10), floor(y / 10))) as cells from pos join truth using (node) group by community"),
    "scatter": plain(EVERY, "select community, round(sqrt(var_pop(x) + var_pop(y)) / (select sqrt(var_pop(x) + var_pop(y)) from pos), 6) as scatter from pos join truth using (node) group by community"),
    "rank_corr": plain(f"{TRUE}, {SIZES}, r as (select rank() over (order by size) + (count(*) over (partition by size) - 1) / 2 as ra, rank() over (order by n_nodes) + (count(*) over (partition by n_nodes) - 1) / 2 as rb from sizes)", "select round(corr(ra, rb), 6) as rho from r"),
    "stable_iteration": plain(traced(4), " union all ".join(f"select cast({eps} as double) as eps, coalesce(max(i), 0) + 1 as stable from trace where m > {eps} * d" for eps in (0.01, 0.1, 0.2))),
    "radius": plain(f"{TRUE}, {SIZES}", "select community, round(sqrt(size), 6) as radius from sizes"),
    "colour_bands": bands("ntile(10) over (partition by tail order by size, community)"),
    "colour_bands_weight": bands("least(cast(floor(10.0 * (sum(size) over (partition by tail order by size, community) - size) / sum(size) over (partition by tail)) as int) + 1, 10)"),
    "colour_bands_log": bands("case when max(log2(size)) over (partition by tail) > min(log2(size)) over (partition by tail) then least(cast(floor(10 * (log2(size) - min(log2(size)) over (partition by tail)) / (max(log2(size)) over (partition by tail) - min(log2(size)) over (partition by tail))) as int) + 1, 10) else 1 end"),
    "sequential_shades": plain(_MANY, "select community, size, cast(ntile(9) over (order by size, community) as int) as shade from sizes"),
    "morton_codes": plain(EVERY, "select node, cast(" + " | ".join(f"(((cast(floor({v} + 128) as bigint) >> {i}) & 1) << {2 * i + k})" for i in range(8) for k, v in enumerate(("x", "y"))) + " as bigint) as code from pos"),
    "extract_community": plain(TRUE, "select e.src, e.dst from e join truth a on e.src = a.node join truth b on e.dst = b.node where a.community = 7 and b.community = 7"),
    "components": plain(f"{PLANTED}, {DEGREES}, nb as (select src as a, dst as b from e union select dst, src from e), reach as (select node, node as seen from deg union select r.node, nb.b from reach r join nb on r.seen = nb.a)", "select node, min(seen) as community from reach group by node"),
    "edge_sample": plain(PLANTED, "select src, dst from e where ((src * 7919 + dst * 104729) % 1000003) % 100 < 20"),
    "degree_filter": plain(f"{PLANTED}, {DEGREES}", "select src, dst from e where src in (select node from deg where deg >= 4) and dst in (select node from deg where deg >= 4)"),
    "attribute_supergraph": plain(f"e as (select distinct o_custkey as src, l_partkey as dst from orders join lineitem on o_orderkey = l_orderkey)", "select cast(c_nationkey as bigint) as src, cast(p_size + 1000 as bigint) as dst, count(*) as w from e join customer on src = c_custkey join part on dst = p_partkey group by 1, 2"),  # noqa: F541
    "scan_edges_pruned": "select l_orderkey as src, l_partkey as dst from lineitem where l_quantity >= 45",
    "json_edges": "select user_id as src, cast(json_extract_string(props, '$.k') as bigint) as dst, count(*) as w from events where json_extract_string(props, '$.k') is not null group by 1, 2",
    "page_link_edges": """select distinct regexp_extract(url, '//([^/]*)', 1) as src, dst from (select url, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as dst from pages) where dst <> '' and regexp_extract(url, '//([^/]*)', 1) <> ''""",
    "knn_edges": "with s as (select a.vec_id as a, b.vec_id as b, list_inner_product(cast(a.embedding as double[]), cast(b.embedding as double[])) as s from embeddings a join embeddings b on a.vec_id % 20 = 0 and a.vec_id <> b.vec_id), n as (select a, b from s qualify row_number() over (partition by a order by s desc, b) <= 5) select distinct least(a, b) as src, greatest(a, b) as dst from n",
    "conversation_edges": "select distinct a.conv_id * 1000 + a.turn as src, b.conv_id * 1000 + b.turn as dst from conversations a join conversations b on a.conv_id = b.conv_id and b.turn = a.turn + 1",
    "document_items": f"select distinct doc_id as src, item_id + {SECOND} as dst from documents d join benchmark b on contains(d.text, b.text)",
    "copurchase_edges": "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey",
    "supplier_part_edges": f"select distinct l_suppkey as src, l_partkey + {SECOND} as dst from lineitem",
    "customer_supplier_edges": f"select distinct o_custkey as src, l_suppkey + {SECOND} as dst from orders join lineitem on o_orderkey = l_orderkey",
    "shared_line_edges": plain(_LINES, "select distinct a.doc_id as src, b.doc_id as dst from sl a join sl b on a.line = b.line and a.doc_id < b.doc_id"),
    "shared_line_hubs": """with ln as (select distinct doc_id, trim(l) as line from (select doc_id, unnest(string_split(text, chr(10))) as l from documents where doc_id is not null) where trim(l) <> ''),
hub as (select line, min(doc_id) as src from ln group by line having count(*) > 1) select distinct src, doc_id as dst from ln join hub using (line) where doc_id <> src""",
    "user_next_edges": plain(_NEXT, "select distinct least(a, b) as src, greatest(a, b) as dst from nx where b is not null and a <> b"),
    "nation_trade": plain(_TRADE, "select * from trade"),
    "sample_edges": "select src, dst from (select distinct l_orderkey as src, l_partkey + 1000000000 as dst from lineitem) where ((src * 7919 + dst * 104729) % 1000003) % 100 < 5",
    "filter_time_slice": """select event_id, user_id from events where ts between timestamp '2024-01-10' and timestamp '2024-01-20' and event_type in ('view', 'click', 'purchase') and props like '%"k"%'""",
    "filter_null_safe_labels": plain(PLANTED, "select src, count(*) as n from (select src, case when dst % 3 = 0 then dst end as x, case when dst % 2 = 0 then dst end as y from e) where x is not distinct from y group by src"),
    "join_shuffle_hash": plain(f"{PLANTED}, {DEGREES}", "select src, dst, deg as src_deg from e join deg on src = node"),
    "degree_band_join": plain(f"{PLANTED}, {DEGREES}", "select band, count(*) as n from deg join (values (1, 1, 2), (2, 3, 5), (3, 6, 1000000)) t(band, low, high) on deg between low and high group by band"),
    "interval_edges": "with e as (select user_id, ts, cast(json_extract_string(props, '$.k') as bigint) as k from events) select a.user_id as src, b.user_id as dst, count(*) as w from e a join e b on a.k = b.k and a.user_id < b.user_id and b.ts between a.ts - interval 1 hour and a.ts + interval 1 hour group by 1, 2",
    "isolated_nodes": plain(PLANTED, f"select p_partkey from part where not exists (select 1 from e where dst = p_partkey + {SECOND})"),
    "top_neighbours": f"with e as (select distinct l_suppkey as src, l_partkey + {SECOND} as dst from lineitem), d as (select dst, count(*) as deg from e group by dst) select src, dst, deg, row_number() over (partition by src order by deg desc, dst) as rank from e join d using (dst) qualify rank <= 3",
    "top_neighbours_lateral": plain(PLANTED, "select src, dst from e qualify row_number() over (partition by src order by dst) <= 2"),
    "community_members_list": plain(TRUE, "select community, array_to_string(list_sort(list(node))[1:10], ',') as members from truth group by community"),
    "community_members_all": plain(TRUE, "select community, node // 1000 as chunk, array_to_string(list_sort(list(node)), ',') as members from truth group by community, chunk"),
    "last_label": plain(f"{PLANTED}, {found()}", "select loser, arg_max(winner, seq) as last, arg_min(winner, seq) as first from ev group by loser"),
    "sizes_rollup": plain(_TYPED, "select community, side, cast(sum(deg) as bigint) as size, count(*) as n from typed group by rollup (community, side)"),
    "edges_cube": plain(_TYPED, "select community, side, max(deg) as most, count(*) as n from typed group by cube (community, side)"),
    "sizes_grouping_sets": plain(_TYPED, "select community, side, cast(sum(deg) as bigint) as size, cast(grouping_id(community, side) as bigint) as gid from typed group by grouping sets ((community), (side), ())"),
    "rounds_pivot": plain(TWO, "select part, cast(sum(n) filter (where r = 1) as bigint) as round_1, cast(sum(n) filter (where r = 2) as bigint) as round_2 from (select 1 as r, community % 5 as part, count(distinct community) as n from alabel group by 2 union all select 2, community % 5, count(distinct community) from blabel group by 2) group by part"),
    "size_rank": plain(f"{TRUE}, {SIZES}", "select community, rank() over w as rank, dense_rank() over w as dense, round(percent_rank() over w, 6) as pr from sizes window w as (order by n_nodes desc)"),
    "size_cumulative_share": plain(f"{TRUE}, {SIZES}", "select community, round(sum(size) over (order by size, community) / (select sum(size) from sizes), 6) as share, round(cume_dist() over (order by size, community), 6) as cd from sizes"),
    "edge_rate_sliding": "select event_id, count(*) over (partition by user_id order by t range between 86400 preceding and current row) as n from (select event_id, user_id, cast(floor(epoch(ts)) as bigint) as t from events)",
    "prev_event": "select event_id, lag(event_id) over w as before, lead(event_id) over w as after, first_value(event_id) over w as first, round(sum(value) over (partition by user_id order by ts, event_id rows between 6 preceding and current row), 4) as v from events window w as (partition by user_id order by ts, event_id)",
    "top_communities": plain(_MANY, "select community, size from sizes order by size desc, community limit 10"),
    "edges_common": f"({_T}) intersect ({_U})",
    "edges_gained": f"({_T}) except all ({_U})",
    "edges_lost": f"({_U}) except ({_T})",
    "edges_union": f"({_T}) union ({_U})",
    "host_of_url": "select page_id, lower(regexp_extract(url, '//([^/]*)', 1)) as host, regexp_extract(regexp_extract(url, '//([^/]*)', 1), '([^.]*\\.[^.]*)$', 1) as domain from pages",
    "node_neighbour_arrays": plain(PLANTED, "select src, count(distinct dst) as n, cast(sum(distinct dst) as bigint) as total, min(dst) as first from e group by src"),
    "metrics_map": plain(f"{TRUE}, {SIZES}", "select community, size, 'n,size' as names from sizes"),
    "community_json": plain(f"{TRUE}, {SIZES}", "select community, size from sizes"),
    "edges_by_month": "select strftime(date_trunc('month', o_orderdate), '%Y-%m') as month, count(*) as n, count(distinct o_custkey) as customers from orders group by 1",
    "edges_tumbling": f"select strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') as start, count(*) as n from ({_EVK}) group by 1",
    "edges_sliding": f"select strftime(time_bucket(interval 6 hours, ts, timestamp '2000-01-01') - to_hours(6 * k), '%Y-%m-%d %H:%M:%S') as start, count(*) as n from ({_EVK}) cross join (values (0), (1), (2), (3)) t(k) group by 1",
    "edges_sessions": f"with x as (select src, ts, case when ts - lag(ts) over (partition by src order by ts) < interval 30 minutes then 0 else 1 end as opens from ({_EVK})), y as (select src, ts, sum(opens) over (partition by src order by ts rows unbounded preceding) as g from x) select src, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*) as n from y group by src, g",
    "sql_function_cells": plain(f"{PLANTED}, {DEGREES}", f"select node, {cell('node', 0)} as cell from deg"),
}
for _depth in (1, 2, 3, 4):
    ORACLES[f"sketch_estimate_d{_depth}"] = plain(f"{PLANTED}, {DEGREES}, {matrix('deg', 'node', 'deg', _depth)}, {estimate('deg', 'node', _depth)}", "select * from est")
