"""DuckDB oracles by brute force: every index vector by self-joins, every concept vector by enumeration."""

from __future__ import annotations

from relseq.workloads import ALL_K2, MG_GRID, MS_GRID, PARTIAL, PARTIAL_SPAN, SPAN_GRID, all_cells

RAW = r"""
raw as (select event_id, user_id, event_type, value, cast(regexp_extract(props, '"k":\s*(\d+)', 1) as int) k, datediff('day', date '2024-01-01', cast(ts as date)) dy from events),
lng as (select user_id || '-' || (dy // {days}) seq_id, dy, case when event_type = 'error' then 'F' else 'A' end type, event_id, value, k, event_type,
  case when event_type = 'error' then array_to_string(string_split(substr(bin(k + 4), 2), ''), '/')
       else (case when event_type in ('view', 'click') then 'engage' else 'convert' end) || '/' || event_type || '/q' || (k // 20) || '/' || lpad(cast(k // 2 as varchar), 2, '0') end concept from raw)"""
EVENTS = (
    RAW
    + """,
uni as (select * from lng qualify row_number() over (partition by seq_id, dy, type, concept order by event_id) = 1),
e as (select seq_id, row_number() over (partition by seq_id order by dy, type, concept, event_id) pos, dense_rank() over (partition by seq_id order by dy) txn, type, concept, event_id, value, k, event_type, dy from uni)"""
)


def events(days: int = 3, where: str | None = None) -> str:
    """WITH list up to ``e``, the canonical events; ``where`` limits sequences."""
    return "with " + EVENTS.format(days=days) + (f", f as (select * from e where seq_id in (select seq_id from e group by seq_id having {where}))" if where else ", f as (select * from e)")


def text(k: int) -> str:
    return "a1.type" + "".join(f" || (case when a{i}.txn > a{i - 1}.txn then ' ; ' else ' ' end) || a{i}.type" for i in range(2, k + 1))


def occ(k: int, gap=None, span=None, extra: str = "", at: str = "pos") -> str:
    """All index vectors of k events under the limits."""
    out = f"select a1.seq_id, {text(k)} skeleton, {k} n_events{extra} from f a1"
    for i in range(2, k + 1):
        out += f" join f a{i} on a{i}.seq_id = a1.seq_id and a{i}.pos > a{i - 1}.pos"
        out += f" and a{i}.{at} - a{i - 1}.{at} <= {gap}" if gap else ""
        out += f" and a{i}.{at} - a1.{at} <= {span}" if span else ""
    return out


def counts(ks, gap=None, span=None) -> str:
    return "select skeleton, n_events, count(distinct seq_id) support, count(*) occurrences from (" + " union all ".join(occ(k, gap, span) for k in ks) + ") group by all"


def theta(ms: float) -> str:
    return f"(select ceil({ms} * count(distinct seq_id) - 1e-9) from f)"


def skeletons(ms: float, gap=None, k: int = 3, span=None, days: int = 3, where: str | None = None) -> str:
    return events(days, where) + f" select skeleton, n_events::int n_events, support, occurrences from ({counts(range(1, k + 1), gap, span)}) where support >= {theta(ms)}"


def relation(i: int, j: int) -> str:
    """Relation concept of events i < j of an occurrence."""
    a, b = f"a{i}", f"a{j}"
    cross = f"case when {a}.k // 10 <> {b}.k // 10 then 'Unmatched' else 'Matched/' || case when fv > av then 'Higher' when fv < av then 'Lower' else 'Equal' end end"
    f_first = cross.replace("fv", f"{a}.value").replace("av", f"{b}.value")
    a_first = cross.replace("fv", f"{b}.value").replace("av", f"{a}.value")
    return f"case when {a}.type = 'A' and {b}.type = 'A' then case when {a}.event_type = {b}.event_type then '=' else '≠' end when {a}.type = 'F' and {b}.type = 'F' then case when {a}.k // 10 = {b}.k // 10 then '=' else '≠' end when {a}.type = 'F' then {f_first} else {a_first} end"


def slots(k: int, concepts: bool, relations: bool) -> list[str]:
    out = []
    for j in range(1, k + 1):
        out += [f"a{j}.concept"] if concepts else []
        out += [relation(i, j) for i in range(1, j)] if relations else []
    return out


def leafs(k: int, gap, concepts: bool, relations: bool, distinct: bool = True, span=None) -> str:
    cols = "".join(f", {s} s{n}" for n, s in enumerate(slots(k, concepts, relations), 1))
    return f"select {'distinct' if distinct else ''} * from ({occ(k, gap, span, cols)})"


def above(c: str) -> str:
    """The concept, its ancestors and the root."""
    parts = f"string_split({c}, '/')"
    return f"list_concat([''], [array_to_string(({parts})[1:i], '/') for i in range(1, len({parts}) + 1)])"


def vectors(k: int, gap, concepts: bool, relations: bool, ms: float, span=None) -> str:
    """(skeleton, v1 .., support) of every frequent vector of k events, from the named CTE ``vec{k}``."""
    n = len(slots(k, concepts, relations))
    names = "".join(f", v{i}" for i in range(1, n + 1))
    # One unnest after the other, so that vectors are all combinations.
    inner = f"({leafs(k, gap, concepts, relations, span=span)})"
    for i in range(1, n + 1):
        inner = f"(select *, unnest({above(f's{i}')}) v{i} from {inner})"
    return f"select skeleton{names}, count(distinct seq_id) support from {inner} group by all having count(distinct seq_id) >= {theta(ms)}"


def frequent_vectors(k: int, gap, concepts: bool, relations: bool, ms: float) -> str:
    """The same for many slots: slots are added one by one, and what is not frequent so far is left out."""
    n = len(slots(k, concepts, relations))
    ctes = [f"x0 as materialized (select *, row_number() over () r from ({leafs(k, gap, concepts, relations)}))"]
    for i in range(1, n + 1):
        names = "".join(f", v{j}" for j in range(1, i + 1))
        ctes.append(f"y{i} as (select *, unnest({above(f's{i}')}) v{i} from x{i - 1})")
        ctes.append(f"g{i} as materialized (select skeleton{names}, count(distinct seq_id) support from y{i} group by all having count(distinct seq_id) >= {theta(ms)})")
        if i < n:
            ctes.append(f"x{i} as materialized (select y{i}.* from y{i} semi join g{i} using (skeleton{names}))")
    return f"with {', '.join(ctes)} select * from g{n}"


def lifted(k: int, n: int, table: str) -> str:
    parts = []
    for i in range(1, n + 1):
        cols = "".join(f", case when instr(v{j}, '/') > 0 then regexp_replace(v{j}, '/[^/]*$', '') else '' end v{j}" if j == i else f", v{j}" for j in range(1, n + 1))
        parts.append(f"select skeleton{cols}, support from {table} where v{i} <> ''")
    return " union all ".join(parts)


def cell(c) -> str:
    """One row for a setting of the grid: skeletons, occurrences and maximal patterns by enumeration."""
    concepts, ks = c.scenario == "full", range(1, c.max_events + 1)
    ctes = [f"f as (select * from e where (string_split(seq_id, '-')[1]::bigint * 7 + string_split(seq_id, '-')[2]::bigint * 3) % 10 < {c.tenths})"]
    ctes.append(f"sk as materialized (select * from ({counts(ks, c.max_gap, c.max_span)}) where support >= {theta(c.min_support)})")
    found = []
    for k in ks:
        n = len(slots(k, concepts, True))
        if not n:
            found.append(f"(select count(*) from sk where n_events = {k})")
            continue
        same = " and ".join(["u.skeleton = x.skeleton", *(f"u.v{i} = x.v{i}" for i in range(1, n + 1))])
        ctes.append(f"vec{k} as materialized ({vectors(k, c.max_gap, concepts, True, c.min_support, c.max_span)})")
        ctes.append(f"up{k} as materialized ({lifted(k, n, f'vec{k}')})")
        found.append(f"(select count(*) from vec{k} x where not exists (select 1 from up{k} u where {same}))")
    numbers = f"{c.min_support}::double ms, {c.max_gap or 0}::int mg, {c.max_span or 0}::int as \"span\", {10 * c.tenths}::int sample_pct"
    return f"(with {', '.join(ctes)} select '{c.workload}' workload, {numbers}, (select count(*) from sk) n_skeletons, (select coalesce(sum(occurrences), 0)::bigint from sk) n_occurrences, ({' + '.join(found)})::bigint n_patterns)"


def grid(sweep: str, kind: str, k: int) -> str:
    cells = [c for c in all_cells(k) if c.scenario == kind and c.workload.startswith(sweep)]
    return "with " + EVENTS.format(days=7 if sweep == "span" else 3) + " " + " union all ".join(f"select * from {cell(c)}" for c in cells)


def capped(ms: float, gap: int, most: int, ks) -> str:
    """Free and capped supports: each level grows from the first ``most`` occurrences of the level before."""
    ctes = [f"c0 as (select *, 'x' dummy from ({counts(ks, gap)}) where support >= {theta(ms)})"]
    ctes.append("g1 as (select seq_id, type skeleton, [pos] lam, pos p, txn t from f)")
    for k in ks:
        ctes.append(f"l{k} as materialized (select skeleton, count(distinct seq_id) support from g{k} group by skeleton having count(distinct seq_id) >= {theta(ms)})")
        ctes.append(f"h{k} as materialized (select * from g{k} semi join l{k} using (skeleton) qualify row_number() over (partition by seq_id, skeleton order by lam) <= {most})")
        ctes.append(f"g{k + 1} as (select h.seq_id, h.skeleton || (case when f.txn > h.t then ' ; ' else ' ' end) || f.type skeleton, list_append(lam, pos) lam, pos p, txn t from h{k} h join f on f.seq_id = h.seq_id and f.pos > h.p and f.pos - h.p <= {gap})")
    # A level's own cap comes after its support was counted, its occurrences are counted before.
    each = " union all ".join(f"select skeleton, count(distinct seq_id) capped_support, count(*) capped_occurrences from g{k} semi join l{k} using (skeleton) group by skeleton" for k in ks)
    return events() + ", " + ", ".join(ctes) + f" select c0.skeleton, n_events::int n_events, support, occurrences, capped_support, capped_occurrences from c0 left join ({each}) using (skeleton)"


PARENTS = """, p2 as (select seq_id, skeleton, a1t t1, sep, a2t t2 from ({pairs})), s2 as (select skeleton, any_value(t1) t1, any_value(sep) sep, any_value(t2) t2 from p2 group by skeleton having count(distinct seq_id) >= {theta}),
c3 as (select a.skeleton x, b.skeleton y, a.t1 || a.sep || a.t2 || b.sep || b.t2 candidate from s2 a join s2 b on a.t2 = b.t1), o as (select distinct seq_id, skeleton from p2)
select candidate, count(*) sequences from c3 join o ox on ox.skeleton = x join o oy on oy.skeleton = y and oy.seq_id = ox.seq_id group by candidate"""

BOUNDS = events() + """, n as (select n::int n from (select count(*) n from f group by seq_id) where n between 3 and 8 group by n), k as (select range::int k from range(2, 4)), l as (select * from (values (0, 0), (2, 0), (3, 0), (0, 4)) t(gap, span)),
o as (select n, 2 k, a.range p1, b.range p2, b.range p3 from n, range(1, 9) a, range(1, 9) b where a.range < b.range and b.range <= n union all
      select n, 3, a.range, b.range, c.range from n, range(1, 9) a, range(1, 9) b, range(1, 9) c where a.range < b.range and b.range < c.range and c.range <= n),
fact as (select n, k, gap, span, (select count(*) from o where o.n = n.n and o.k = k.k and (gap = 0 or (p2 - p1 <= gap and p3 - p2 <= gap)) and (span = 0 or p3 - p1 <= span)) as exact from n, k, l)
select n, k, gap::int gap, span::int as "span", exact, (case when gap > 0 then gap ** (k - 1) * (n - k + 1) when span > 0 then (case k when 2 then span else span * (span - 1) / 2 end) * (n - k + 1) else (case k when 2 then n * (n - 1) / 2 else n * (n - 1) * (n - 2) / 6 end) end)::bigint corrected,
 (case when gap > 0 then (gap - 1) ** (k - 1) * (n - k) when span > 0 then (case k when 2 then span else span * (span - 1) / 2 end) * (n - k) else (case k when 2 then n * (n - 1) / 2 else n * (n - 1) * (n - 2) / 6 end) end)::bigint published from fact"""


def refined(kind: str, ks, gap, ms: float, concepts: bool, relations: bool) -> str:
    ctes, parts = [], []
    for k in ks:
        n = len(slots(k, concepts, relations))
        many = (frequent_vectors if n > 3 else vectors)(k, gap, concepts, relations, ms)
        ctes.append(f"vec{k} as materialized ({many})")
        shown = " || '|' || ".join(f"v{i}" for i in range(1, n + 1))
        keep = ""
        if kind != "all":
            ctes.append(f"up{k} as materialized ({lifted(k, n, f'vec{k}')})")
            same = " and ".join(["u.skeleton = x.skeleton", *(f"u.v{i} = x.v{i}" for i in range(1, n + 1))])
            keep = f" where not exists (select 1 from up{k} u where {same}{' and u.support = x.support' if kind == 'closed' else ''})"
        parts.append(f"select skeleton, {shown} as vector, support from vec{k} x{keep}")
    return events() + ", " + ", ".join(ctes) + " " + " union all ".join(parts)


def items(gap, ms: float, concepts: bool, relations: bool, k: int = 2) -> str:
    """(skeleton, slot, concept, seq_id, row) for skeletons of k events that are frequent."""
    n = len(slots(k, concepts, relations))
    base = f"l as (select *, row_number() over () r from ({leafs(k, gap, concepts, relations, False)})), fr as (select skeleton from l group by skeleton having count(distinct seq_id) >= {theta(ms)})"
    parts = " union all ".join(f"select skeleton, {i} slot, seq_id, r, unnest({above(f's{i}')}) concept from l where skeleton in (select skeleton from fr)" for i in range(1, n + 1))
    return f"{base}, it as (select * from ({parts}) where concept <> '')"


def quoted(names) -> str:
    return ", ".join(f"'{n}'" for n in names)


def _stats(name: str, paths: str) -> str:
    return f"""(with p as (select distinct c from ({paths})), n as (select distinct unnest({above('c')}) c from p),
 l as (select c, case when c = '' then 0 else len(string_split(c, '/')) end depth, not exists (select 1 from n m where m.c <> '' and (case when instr(m.c, '/') > 0 then regexp_replace(m.c, '/[^/]*$', '') else '' end) = n.c) leaf from n)
 select '{name}' tax_id, max(depth) filter (leaf)::int max_depth, min(depth) filter (leaf)::int min_depth, round(avg(depth) filter (leaf), 6) avg_depth, round(stddev_pop(depth) filter (leaf), 6) std_depth, count(*) filter (leaf) leaves, count(*) nodes from l)"""


def oracle_sql() -> dict[str, str]:
    e = events()
    out = {
        "corpus_profile": e + " select count(distinct seq_id) sequences, count(*) events, round(count(*) / count(distinct seq_id), 6) mean_events, (select max(c)::int from (select count(*) c from f group by seq_id)) max_events, (select sum(t)::bigint from (select max(txn) t from f group by seq_id)) transactions, count(*) filter (type = 'A') \"n_A\", count(*) filter (type = 'F') \"n_F\" from f",
        "length_histogram": e + ", n as (select seq_id, count(*)::int n, (count(*) filter (type = 'A'))::int a, (count(*) filter (type = 'F'))::int b from f group by seq_id) select 'all' type, n n_events, count(*) sequences from n group by n union all select 'A', a, count(*) from n group by a union all select 'F', b, count(*) from n group by b",
        "canonical_events": e + " select seq_id, pos::int pos, txn::int txn, type, concept, event_id from f",
        "type_view": e + ", t as (select *, lag(txn) over (partition by seq_id order by pos) lt from f) select seq_id, string_agg((case when lt is null then '' when lt = txn then ' ' else ' ; ' end) || type, '' order by pos) view, count(*)::int n_events, (count(*) + max(txn) - 1)::int n_elements from t group by seq_id",
        "element_index": e + " select seq_id, pos::int pos, (pos + txn - 1)::int element from f",
        "relation_profile": e + f" select least(a1.type, a2.type) type_a, greatest(a1.type, a2.type) type_b, {relation(1, 2)} concept, count(*) pairs from f a1 join f a2 on a1.seq_id = a2.seq_id and a1.pos < a2.pos group by all",
        "full_view_sizes": e + " select seq_id, (count(*) * (count(*) - 1) // 2)::int relations from f group by seq_id",
        "taxonomy_stats": e + " " + " union all ".join([
            _stats("action", "select concept c from lng where type = 'A'"), _stats("fault", "select concept c from lng where type = 'F'"), _stats("part", "select p_type || '/' || p_brand || '/' || p_partkey c from part"),
            _stats("cross", "select unnest(['Matched/Higher', 'Matched/Equal', 'Matched/Lower', 'Unmatched']) c"), _stats("identity", "select unnest(['=', '≠']) c")]),
        "taxonomy_closure_geo": f"with p as (select r_name || '/' || n_name c from nation join region on n_regionkey = r_regionkey), n as (select distinct unnest({above('c')}) c from p), a as (select c, unnest({above('c')}) x from n where c <> '' union all select '', '') select c concept, x ancestor, ((case when c = '' then 0 else len(string_split(c, '/')) end) - (case when x = '' then 0 else len(string_split(x, '/')) end))::int distance from a",
        "taxonomy_heap": _stats("fault", r"""select array_to_string(string_split(substr(bin(cast(regexp_extract(props, '"k":\s*(\d+)', 1) as int) + 4), 2), ''), '/') c from events""")[1:-1],
        "dag_common_ancestor": "with n as (select p_partkey b, lag(p_partkey) over (order by p_partkey) a, p_type t, p_brand r, lag(p_type) over (order by p_partkey) pt, lag(p_brand) over (order by p_partkey) pr from part), s as (select a, b, list_sort(list_distinct(list_intersect([t, r], [pt, pr]))) s from n where a is not null) select 'part ' || a a, 'part ' || b b, coalesce(s[1], 'Any') common, case when len(s) = 0 then 'Any' else array_to_string(s, ' & ') end conjunction from s",
        "occurrences_k2": e + " select seq_id, skeleton, p positions from (" + occ(2, 1, None, ", a1.pos || ',' || a2.pos p") + f") where skeleton in ({quoted(ALL_K2)})",
        "occurrences_span": e + " select seq_id, skeleton, p positions from (" + occ(3, None, 4, ", a1.pos || ',' || a2.pos || ',' || a3.pos p") + ") where skeleton in ('A ; A ; F', 'A A F', 'F ; A ; A')",
        "occurrences_units": events() .replace("f as (select * from e)", "f as (select *, pos + txn - 1 element from e)") + " " + " union all ".join(f"select skeleton, count(*) occurrences, '{u}' unit from ({occ(2, 2, None, '', at)}) where skeleton = 'A ; F' group by skeleton" for u, at in (("event", "pos"), ("element", "element"), ("transaction", "txn"), ("time", "dy"))),
        "multiset_candidates": e + ", n as (select seq_id, count(*) filter (type = 'A') a, count(*) filter (type = 'F') b from f group by seq_id) " + " union all ".join(f"select '{s}' skeleton, count(*) sequences from n where a >= {s.count('A')} and b >= {s.count('F')}" for s in ("A ; F", "F ; F", "A A A", "F ; F ; F", "A ; A ; F")),
        "skeletons_ms_sweep": e + f", c as (select * from ({counts((1, 2, 3))})) " + " union all ".join(f"select n_events::int n_events, count(*) skeletons, sum(occurrences)::bigint occurrences, {ms}::double ms from c where support >= {theta(ms)} group by n_events" for ms in MS_GRID),
        "skeletons_span_sweep": events(7) + " " + " union all ".join(f"select n_events::int n_events, count(*) skeletons, sum(occurrences)::bigint occurrences, {ms}::double ms, {w}::int as \"span\" from ({counts((1, 2, 3), None, w)}) where support >= {theta(ms)} group by n_events" for ms in (0.10, 0.18) for w in SPAN_GRID),
        "skeletons_k4_ms18_mg3": skeletons(0.18, 3, 4),
        "skeletons_size_sweep": "with " + EVENTS.format(days=3) + ", " + ", ".join(f"f{t} as (select * from e where (string_split(seq_id, '-')[1]::bigint * 7 + string_split(seq_id, '-')[2]::bigint * 3) % 10 < {t})" for t in range(1, 11)) + " " + " union all ".join(f"select skeleton, n_events::int n_events, support, occurrences, {t}::int tenths from ({counts((1, 2, 3), 3)}) where support >= {theta(0.10)}".replace(" f ", f" f{t} ").replace(" f)", f" f{t})") for t in range(1, 11)),
        "skeletons_dialogues": DIALOGUES + f" select skeleton, n_events::int n_events, support, occurrences from ({counts((1, 2, 3), 3)}) where support >= {theta(0.10)}",
        "skeletons_orders_year": ORDERS + f" select skeleton, n_events::int n_events, support, occurrences from ({counts((1, 2, 3), 3)}) where support >= {theta(0.10)}",
        "refine_all_rel_k3": refined("all", (2, 3), 3, 0.10, False, True),
        "refine_closed_rel_k3": refined("closed", (2, 3), 3, 0.10, False, True),
        "refine_maximal_rel_k3": refined("maximal", (2, 3), 3, 0.10, False, True),
        "refine_maximal_rel_k3_backtrack": refined("maximal", (2, 3), 3, 0.10, False, True),
        "refine_maximal_rel_k3_levelwise": refined("maximal", (2, 3), 3, 0.18, False, True),
        "refine_maximal_rel_k3_partitioned": refined("maximal", (2, 3), 3, 0.10, False, True),
        "refine_all_full_k2": refined("all", (2,), 3, 0.10, True, True),
        "refine_closed_full_k2": refined("closed", (2,), 3, 0.10, True, True),
        "refine_maximal_full_k2": refined("maximal", (2,), 3, 0.10, True, True),
        "refine_taxonomic_only_k2": refined("maximal", (2,), 3, 0.10, True, False),
        "item_support": e + ", " + items(3, 0.10, True, True) + " select skeleton, slot::int slot, concept, count(distinct seq_id) support from it group by all",
        "item_vocabulary": e + ", " + items(1, 0.10, True, True) + " select skeleton, (row_number() over (partition by skeleton order by slot, concept))::int item_id, slot::int slot, concept from (select distinct skeleton, slot, concept from it)",
        "row_vs_sequence_support": e + ", " + items(3, 0.10, False, True) + " select skeleton, slot::int slot, concept, count(*) row_support, count(distinct seq_id) support from it group by all",
        "first_occurrence_loss": e + ", " + items(3, 0.10, False, True).replace("row_number() over () r from (select", "row_number() over (partition by seq_id, skeleton order by p1, p2) r from (select").replace("n_events, case", "n_events, a1.pos p1, a2.pos p2, case") + " select skeleton, slot::int slot, concept, count(distinct seq_id) support, count(distinct seq_id) filter (r = 1) first_support from it group by all",
        "specialised_share": refined("maximal", (2,), 3, 0.10, True, True).replace(" select skeleton, v1 || '|' || v2 || '|' || v3 as vector, support from vec2 x", " select count(*) patterns, count(*) filter (v1 <> '' or v2 <> '') specialised, round(avg((v1 <> '' or v2 <> '')::int::double), 6) share from vec2 x"),
        "topk_patterns": "select * from (select *, (row_number() over (partition by skeleton order by support desc, vector))::int place from (" + refined("maximal", (2,), 3, 0.10, True, True) + ")) where place <= 5",
        "example_patterns": e + f" select 'fault, later matched action' pattern, count(distinct a1.seq_id) support from f a1 join f a2 on a1.seq_id = a2.seq_id and a2.txn > a1.txn where a1.type = 'F' and a2.type = 'A' and a1.k // 10 = a2.k // 10 union all select 'two actions, then a fault of one kind', count(distinct a1.seq_id) from f a1 join f a2 on a1.seq_id = a2.seq_id and a2.txn > a1.txn join f a3 on a3.seq_id = a1.seq_id and a3.txn > a2.txn where a1.type = 'A' and a2.type = 'A' and a3.type = 'F' and (a3.concept = '0/1' or a3.concept like '0/1/%') and a3.k // 10 = a1.k // 10",
        "rollup_support_by_level": e + ", p as (select seq_id, string_split(concept, '/') s from f where type = 'A') select s[1] as family, s[2] as kind, s[3] as \"quarter\", count(distinct seq_id) support from p group by rollup (s[1], s[2], s[3])",
        "presence_vs_occurrences": e + f" select skeleton, count(distinct seq_id) support, count(*) occurrences from ({occ(2, 2)}) where skeleton in ({quoted(ALL_K2)}) group by skeleton",
        "presence_forward": e + f" select skeleton, count(distinct seq_id) support from ({occ(2, 2)}) where skeleton in ({quoted(ALL_K2)}) group by skeleton",
        "pattern_growth": e + f" select skeleton, support from ({counts((1, 2, 3))}) where support >= {theta(0.10)}",
        "pattern_growth_mg2": e + f" select skeleton, support from ({counts((1, 2, 3), 2)}) where support >= {theta(0.10)}",
        "crowded_remedy": skeletons(0.10, 3, 3, where="count(*) filter (type = 'A') <= 6 and count(*) filter (type = 'F') <= 6"),
        "long_remedy": skeletons(0.10, 3, 3, where="count(*) <= 8"),
        "run_length_remedy": skeletons(0.10, 3, 3) + " and not regexp_matches(skeleton, '(A[ ;]+){2}A|(F[ ;]+){2}F')",
        "stream_equals_batch": e + f", b as (select skeleton, count(distinct seq_id) support, count(*) occurrences from ({occ(2, 2)}) where skeleton in ('A ; F', 'A A', 'F ; A') group by skeleton) select skeleton, support, occurrences, support batch_support, occurrences batch_occurrences from b",
        "gap_subpattern_violations": e + f", c as (select * from ({counts((2, 3), 1)})), v as (select skeleton, support, string_split(skeleton, ' ') s from c where n_events = 3 and support >= {theta(0.10)}), w as (select skeleton, support, s[1] || (case when contains(skeleton, ';') then ' ; ' else ' ' end) || s[len(s)] sub_pattern from v) select w.skeleton, w.support, sub_pattern, coalesce(c.support, 0) sub_support from w left join c on c.skeleton = sub_pattern where coalesce(c.support, 0) < {theta(0.10)}",
        "generic_refinement": "with l as (select distinct l_orderkey s, p_type || '/' || p_brand a, l_returnflag b, l_linestatus c from lineitem join part on l_partkey = p_partkey), v as (select s, unnest(" + above("a") + ") v1, b, c from l), w as (select s, v1, unnest(['', b]) v2, c from v), x as (select s, v1, v2, unnest(['', c]) v3 from w), g as (select v1, v2, v3, count(distinct s) support from x group by all having count(distinct s) >= 600), u as (select case when instr(v1, '/') > 0 then regexp_replace(v1, '/[^/]*$', '') else '' end v1, v2, v3 from g where v1 <> '' union select v1, '', v3 from g where v2 <> '' union select v1, v2, '' from g where v3 <> '') select 'line' skeleton, v1 || '|' || v2 || '|' || v3 as vector, support from g where not exists (select 1 from u where u.v1 = g.v1 and u.v2 = g.v2 and u.v3 = g.v3)",
    }
    three = e + f" select skeleton, count(*) occurrences, count(distinct seq_id) support from ({occ(3, 2)}) group by skeleton"
    out |= {k: three for k in ("occurrences_k3_gap2", "occurrences_k3_gap2_kernel", "occurrences_k3_gap2_join")}
    out |= {f"skeletons_k3_ms10_mg{g}": skeletons(0.10, g) for g in MG_GRID}
    out |= {f"grid_{sweep}_{kind}_k{k}": grid(sweep, kind, k) for sweep in ("gap", "span", "support", "size") for kind, k in (("relations", 3), ("full", 2))}
    out |= {"skeletons_all_ms18_mg1": skeletons(0.18, 1, 8), "skeletons_all_ms18_mg3": skeletons(0.18, 3, 8), "skeletons_all_ms10_mg3": skeletons(0.10, 3, 8)}
    out |= {name: refined("maximal", (2, 3), 3, 0.10, True, True) for name in ("refine_maximal_full_k3", "refine_maximal_full_k3_partitioned")}
    one, three_ = (refined("maximal", (2,), g, 0.10, False, True) for g in (1, 3))
    out["pattern_set_changes"] = f"select skeleton, vector, a.support support_a, b.support support_b, case when a.support is null then 'new' when b.support is null then 'gone' when a.support < b.support then 'more' when a.support > b.support then 'less' else 'same' end change from ({one}) a full join ({three_}) b using (skeleton, vector)"
    out["pattern_set_operations"] = f"with a as ({one}), b as ({three_}) select 'union' operation, skeleton, vector, max(support) support from (select * from a union all select * from b) group by skeleton, vector union all select 'intersection', * from a semi join b using (skeleton, vector) union all select 'difference', * from a anti join b using (skeleton, vector)"
    exact = e + ", " + items(3, 0.10, True, True)
    out["approximate_item_support"] = exact + " select skeleton, slot::int slot, concept, count(distinct seq_id) support, true near from it group by all"
    out["item_support_cube"] = exact + ", s as (select skeleton, slot::int slot, len(string_split(concept, '/'))::int depth, count(distinct seq_id) support from it group by skeleton, slot, concept, depth) select skeleton, slot, depth, count(*) concepts, max(support) best_support, round(100 * max(support) / (select count(distinct seq_id) from f), 4) best_pct from s group by cube (skeleton, slot, depth)"
    out["outlier_cut"] = e + ", n as (select count(*) n from f group by seq_id), c as (select min(n) m from (select n, cume_dist() over (order by n) c from n) where c >= 0.95) select count(*) sequences, sum(n)::bigint events, any_value(m)::int longest from n, c where n <= m"
    out["length_bands"] = e + ", n as (select count(*) n from f group by seq_id) select ((n - 1) // 3)::int band, ((n - 1) // 3 * 3 + 1)::int from_events, count(*) sequences from n group by all"
    out["event_gaps"] = e + ", g as (select dy - lag(dy) over (partition by seq_id order by pos) day_gap from f) select day_gap::int day_gap, count(*) events from g group by all"
    found = []
    for names in PARTIAL:
        joins = "".join(f" join events e{i} on e{i}.user_id = e0.user_id and (e{i}.ts, e{i}.event_id) > (e{i - 1}.ts, e{i - 1}.event_id) and e{i}.event_type = '{t}' and epoch(e{i}.ts) - epoch(e0.ts) <= {PARTIAL_SPAN}" for i, t in enumerate(names) if i)
        found.append(f"select '{' ; '.join(names)}' skeleton, count(*) occurrences, count(distinct e0.user_id) users from events e0{joins} where e0.event_type = '{names[0]}' having count(*) > 0")
    out["stream_partial_matches"] = " union all ".join(found)
    anc = f"case when n.c = '' then type else type || ':' || n.c end"
    out["extended_form"] = e + f", n as (select seq_id, txn, type, unnest({above('concept')}) c from f), i as (select distinct seq_id, txn, {anc} item from n), p as (select a.seq_id, a.item || ' ; ' || b.item pattern from i a join i b on a.seq_id = b.seq_id and b.txn > a.txn) select pattern, count(distinct seq_id) support from p group by pattern having count(distinct seq_id) >= {theta(0.10)}"
    pairs = occ(2, 3, None, ", a1.type a1t, case when a2.txn > a1.txn then ' ; ' else ' ' end sep, a2.type a2t")
    out["parent_lists"] = e + PARENTS.format(pairs=pairs, theta=theta(0.10))
    out["complexity_bounds"] = BOUNDS
    out["cap_remedy"] = capped(0.10, 3, 2, range(1, 9))
    return out


DIALOGUES = "with e as (select conv_id::varchar seq_id, row_number() over (partition by conv_id order by turn, role) pos, dense_rank() over (partition by conv_id order by turn) txn, role as type from conversations), f as (select * from e)"
ORDERS = """with o as (select o_custkey || '-' || year(o_orderdate) seq_id, cast(o_orderdate as date) dy, 'O' as type, o_orderpriority c1, o_orderstatus c2, o_orderkey id from orders),
l as (select o.seq_id, cast(l_shipdate as date) dy, 'L' as type, p_type || '/' || p_brand || '/' || p_partkey c1, r_name || '/' || n_name || '/' || s_name c2, l_orderkey * 1000 + l_linenumber id
 from lineitem join o on l_orderkey = o.id join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey),
u as (select * from (select * from o union all select * from l) qualify row_number() over (partition by seq_id, dy, type, c1, c2 order by id) = 1),
e as (select seq_id, row_number() over (partition by seq_id order by dy, type, c1, c2, id) pos, dense_rank() over (partition by seq_id order by dy) txn, type from u), f as (select * from e)"""
