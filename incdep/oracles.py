"""DuckDB SQL that computes the same answers by brute force, for the registered queries."""

from __future__ import annotations

from .catalog import CORE, EXTRA
from .workloads import BRAND, DECLARED, HIGH_ARITY, PROSE

# The atomic columns of the given tables.
COLUMNS = {
    "region": "r_regionkey r_name",
    "nation": "n_nationkey n_name n_regionkey",
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment",
    "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate",
    "events": "event_id ts user_id event_type value props",
    "documents": "doc_id text lang source n_chars",
    "embeddings": "vec_id label",
    "pages": "page_id url html",
    "benchmark": "item_id text",
    "labels": "doc_id quality toxic",
    "conversations": "conv_id turn role text",
}
TYPES = {"double": "value c_acctbal s_acctbal p_retailprice o_totalprice l_quantity l_extendedprice l_discount l_tax", "timestamp": "ts o_orderdate l_shipdate"}
TEXT = "r_name n_name c_name c_mktsegment s_name p_name p_brand p_type o_orderstatus o_orderpriority l_returnflag l_linestatus event_type props text lang source url html role"

Tables = dict[str, tuple[str, list[str]]]  # name to (relation, columns)


def tables(names) -> Tables:
    return {n: (n, COLUMNS[n].split()) for n in names}


def numbered(t: Tables) -> list[tuple[int, str, str, str]]:
    """(attr, table, relation, column)."""
    out = []
    for n in sorted(t):
        for c in t[n][1]:
            out.append((len(out), n, t[n][0], c))
    return out


def token(c: str) -> str:
    return f"case when {c} is null then 'n' when length({c}::varchar) > 64 then 'x' || sha256({c}::varchar) else 'v' || {c}::varchar end"


def names_sql(t: Tables) -> str:
    return "select * from (values " + ", ".join(f"({k}, '{n}', '{c}')" for k, n, _, c in numbered(t)) + ") x(attr, t, c)"


def cells_sql(t: Tables) -> str:
    return " union all ".join(f'select {k} attr, {token(chr(34) + c + chr(34))} v from {rel}' for k, _, rel, c in numbered(t))


def masks_sql(cells: str, n: int, prefix: str = "") -> str:
    """CTEs ending in {prefix}pairs(dep, ref): inclusions among the numbers 0..n-1 of cells(attr, v)."""
    words = range(-(-n // 60))
    test = lambda rel, i: "(" + " or ".join(f"({i} // 60 = {w} and ({rel}.w{w} >> ({i} % 60)) & 1 = 1)" for w in words) + ")"
    ors = ", ".join(f"bit_or(case when attr // 60 = {w} then 1::bigint << (attr % 60)::int else 0 end) w{w}" for w in words)
    ands = ", ".join(f"bit_and(w{w}) w{w}" for w in words)
    cols = ", ".join(f"w{w}" for w in words)
    p = prefix
    return f"""{p}cells as ({cells}),
{p}masks as (select distinct {cols} from (select v, {ors} from {p}cells group by v)),
{p}member as (select i::int attr, {cols} from {p}masks m, range({n}) r(i) where {test("m", "i")}),
{p}meet as (select attr, {ands} from {p}member group by attr),
{p}pairs as (select a.attr dep, i::int ref from {p}meet a, range({n}) r(i) where {test("a", "i")} and i <> a.attr)"""


def unary_sql(t: Tables, where: str = "true") -> str:
    return f"""with {masks_sql(cells_sql(t), len(numbered(t)))}, names as ({names_sql(t)})
select d.t dep_table, d.c dep_cols, r.t ref_table, r.c ref_cols, 1 arity
from pairs p join names d on d.attr = p.dep join names r on r.attr = p.ref where {where}"""


def binary_sql(t: Tables) -> str:
    """Unary and binary dependencies, all column pairs of a table compared."""
    cells, combos = [], []
    for n in sorted(t):
        rel, cols = t[n]
        for a in range(len(cols)):
            for b in range(len(cols)):
                if a != b:
                    one, two = token(f'"{cols[a]}"'), token(f'"{cols[b]}"')
                    cells.append(f"select {len(combos)} attr, concat(length({one}), ':', {one}, length({two}), ':', {two}) v from {rel}")
                    combos.append((n, cols[a], cols[b], a < b))
    rows = ", ".join(f"({k}, '{n}', '{a}', '{b}', {str(up).lower()})" for k, (n, a, b, up) in enumerate(combos))
    return f"""{unary_sql(t)} union all (with {masks_sql(" union all ".join(cells), len(combos), "b")},
combos as (select * from (values {rows}) x(k, t, a, b, up))
select d.t, d.a || ',' || d.b, r.t, r.a || ',' || r.b, 2
from bpairs p join combos d on d.k = p.dep and d.up join combos r on r.k = p.ref
where not (d.t = r.t and (d.a in (r.a, r.b) or d.b in (r.a, r.b))))"""


def candidates2_sql(t: Tables) -> str:
    return f"""with {masks_sql(cells_sql(t), len(numbered(t)))}, names as ({names_sql(t)}),
u as (select d.attr a, d.t dt, d.c dc, r.attr b, r.t rt, r.c rc from pairs p join names d on d.attr = p.dep join names r on r.attr = p.ref)
select x.dt dep_table, x.dc || ',' || y.dc dep_cols, x.rt ref_table, x.rc || ',' || y.rc ref_cols, 2 arity
from u x join u y on x.dt = y.dt and x.rt = y.rt and x.a < y.a and x.b <> y.b
where x.a not in (x.b, y.b) and y.a not in (x.b, y.b)"""


def dedupe_sql(t: Tables) -> str:
    return f"""with cells as ({cells_sql(t)}), names as ({names_sql(t)})
select t table_name, c column_name, count(distinct v) distinct_values, min(v) min_v, max(v) max_v from cells join names using (attr) group by t, c"""


def stats_sql(t: Tables) -> str:
    return f"""with cells as ({cells_sql(t)}), names as ({names_sql(t)})
select t table_name, c column_name, count(*) "rows", count(*) filter (v = 'n') nulls, count(distinct v) distinct_values, min(v) min_v, max(v) max_v
from cells join names using (attr) group by t, c"""


def sets_sql(t: Tables) -> str:
    return f"""with cells as ({cells_sql(t)}), s as (select v, list_sort(list(distinct attr)) m from cells group by v)
select array_to_string(m, ',') members, count(*) n_values from s group by m"""


def level_ctes(t: Tables, most: int) -> str:
    """CTEs c2, v2, ... up to ``most`` columns: closed candidates and valid dependencies (dt, d, rt, r), d and r being positions of columns; v1 is unary."""
    rows = " union all ".join(f"select distinct '{n}' t, [{', '.join(token(chr(34) + c + chr(34)) for c in cols)}] vals from {rel}" for n, (rel, cols) in sorted(t.items()))
    place = ", ".join(f"({k}, '{n}', {t[n][1].index(c) + 1})" for k, n, _, c in numbered(t))
    out = [f"""{masks_sql(cells_sql(t), len(numbered(t)))}, place as (select * from (values {place}) x(attr, t, p)), vals as materialized ({rows}),
v1 as materialized (select a.t dt, [a.p] d, b.t rt, [b.p] r from pairs x join place a on a.attr = x.dep join place b on b.attr = x.ref)"""]
    for k in range(1, most):
        out.append(f"""j{k + 1} as materialized (
  select row_number() over () id, a.dt, list_append(a.d, b.d[{k}]) d, a.rt, list_append(a.r, b.r[{k}]) r from v{k} a join v{k} b
    on a.dt = b.dt and a.rt = b.rt and a.d[1:{k - 1}] = b.d[1:{k - 1}] and a.r[1:{k - 1}] = b.r[1:{k - 1}] and a.d[{k}] < b.d[{k}] and not list_contains(a.r, b.r[{k}])
  where a.dt <> a.rt or not list_has_any(list_append(a.d, b.d[{k}]), list_append(a.r, b.r[{k}]))),
c{k + 1} as materialized (
  select * from j{k + 1} where id in (
    select x.id from (select id, dt, rt, list_concat(d[1:g - 1], d[g + 1:]) d, list_concat(r[1:g - 1], r[g + 1:]) r from j{k + 1}, range(1, {k + 2}) y(g)) x
    join v{k} w on w.dt = x.dt and w.rt = x.rt and w.d = x.d and w.r = x.r group by x.id having count(*) = {k + 1})),
v{k + 1} as materialized (
  select dt, d, rt, r from c{k + 1} where id not in (select id from (
    select c.id, list_transform(c.d, lambda i: l.vals[i]) v from c{k + 1} c join vals l on l.t = c.dt
    except select c.id, list_transform(c.r, lambda i: l.vals[i]) v from c{k + 1} c join vals l on l.t = c.rt)))""")
    return ",\n".join(out)


def nary_sql(t: Tables, most: int) -> str:
    """Dependencies of up to ``most`` columns, level by level; every candidate is tested by EXCEPT."""
    cols = ", ".join(f"('{n}', [{', '.join(chr(39) + c + chr(39) for c in cols)}])" for n, (_, cols) in t.items())
    every = " union all ".join(f"select dt, d, rt, r, {k} arity from v{k}" for k in range(1, most + 1))
    named = lambda x, y: f"array_to_string(list_transform({x}, lambda i: {y}.c[i]), ',')"
    return f"""with {level_ctes(t, most)}, cols as (select * from (values {cols}) x(t, c))
select dt dep_table, {named("d", "a")} dep_cols, rt ref_table, {named("r", "b")} ref_cols, arity from ({every}) e join cols a on a.t = e.dt join cols b on b.t = e.rt"""


def most_columns(t: Tables) -> int:
    """Columns of the widest dependency that can be: its sides are of two tables, or apart within one."""
    widths = sorted((len(cols) for _, cols in t.values()), reverse=True)
    return max(widths[0] // 2, *widths[1:2])


def level_counts_sql(sets: dict[str, tuple[Tables, int]]) -> str:
    parts = []
    for name, (t, most) in sets.items():
        n = len(numbered(t))
        counts = f"select 1 arity, {n * (n - 1)} candidates, (select count(*) from v1) valid" + "".join(f" union all select {k}, (select count(*) from c{k}), (select count(*) from v{k})" for k in range(2, most + 1))
        parts.append(f"(with {level_ctes(t, most)} select '{name}' dataset, arity, candidates::bigint candidates, valid from ({counts}) where candidates > 0)")
    return " union all ".join(parts)


def guard_sql(width: int) -> str:
    """Column j of ``width`` residues is included in column k exactly if j < k; the binary candidates that follow, whose validity isn't asked."""
    return f"""with p as (select d.i d, r.i r from range({width}) d(i), range({width}) r(i) where d.i < r.i),
c as (select count(*) n from p a join p b on a.d < b.d and a.r <> b.r and a.d not in (a.r, b.r) and b.d not in (a.r, b.r))
select 1 arity, {width * (width - 1)}::bigint candidates, (select count(*) from p) valid union all select 2, n, null from c"""


def lookups_sql(t: Tables) -> str:
    return " union all ".join(f"select '{n}' table_name, {len(cols)}::bigint combos, count(*) row_count, (count(*) * {len(cols)})::bigint lookups from {rel}" for n, (rel, cols) in t.items())


def profile_sql(sets: dict[str, tuple[Tables, int]]) -> str:
    parts = []
    for name, (t, most) in sets.items():
        rows = " + ".join(f"(select count(*) from {rel})" for rel, _ in t.values())
        chars = " + ".join("(select " + " + ".join(f'coalesce(sum(length("{c}"::varchar)), 0)' for c in cols) + f" from {rel})" for rel, cols in t.values())
        every = " + ".join(f"(select count(*) from v{k})" for k in range(1, most + 1))
        arity = "greatest(" + ", ".join(f"(select {k} * (count(*) > 0)::int from v{k})" for k in range(1, most + 1)) + ")"
        nary, top = (f"({every})::bigint", f"{arity}::int") if most > 1 else ("null::bigint", "null::int")
        parts.append(f"""(with {level_ctes(t, most)} select '{name}' dataset, {len(t)}::bigint "tables", {len(numbered(t))}::bigint attributes, ({rows})::bigint "rows",
({chars})::bigint text_chars, (select count(*) from v1) unary_inds, {nary} nary_inds, {top} max_arity)""")
    return " union all ".join(parts)


def shared_ctes(t: Tables) -> str:
    return f"""cells as ({cells_sql(t)}), names as ({names_sql(t)}), d as materialized (select distinct attr, v from cells),
n as (select attr, count(*) n from d group by attr),
s as (select x.attr dep, y.attr ref, count(*) c from d x join d y on x.v = y.v and x.attr <> y.attr group by all)"""


def partial_sql(t: Tables, eps: float) -> str:
    return f"""with {shared_ctes(t)}
select a.t dep_table, a.c dep_cols, b.t ref_table, b.c ref_cols, n.n dep_distinct, n.n - s.c missing, (n.n - s.c)::double / n.n error
from s join n on n.attr = s.dep join names a on a.attr = s.dep join names b on b.attr = s.ref where (n.n - s.c)::double / n.n <= {eps}"""


def fk_sql(t: Tables) -> str:
    return f"""with {shared_ctes(t)},
r as (select attr, count(*) "rows", count(*) filter (v = 'n') nulls from cells group by attr),
f as (
  select a.t dep_table, a.c dep_col, b.t ref_table, b.c ref_col, s.dep, s.ref, n.n::double / m.n coverage,
    levenshtein(regexp_replace(a.c, '^[a-z]+_', ''), regexp_replace(b.c, '^[a-z]+_', ''))::int name_distance
  from s join n on n.attr = s.dep and n.n = s.c join n m on m.attr = s.ref join r on r.attr = s.ref and r."rows" = m.n and r.nulls = 0
  join names a on a.attr = s.dep join names b on b.attr = s.ref)
select dep_table, dep_col, ref_table, ref_col, name_distance, coverage,
  (row_number() over (partition by dep order by name_distance, coverage desc, ref))::int place from f"""


def classes_sql(t: Tables) -> str:
    return f"""with {masks_sql(cells_sql(t), len(numbered(t)))}, names as ({names_sql(t)}),
m as (select p.dep, min(p.ref) m from pairs p join pairs q on p.dep = q.ref and p.ref = q.dep group by p.dep)
select a.t table_name, a.c column_name, least(a.attr, coalesce(m.m, a.attr)) class_id from names a left join m on m.dep = a.attr"""


def reduced_sql(t: Tables) -> str:
    return f"""with {masks_sql(cells_sql(t), len(numbered(t)))}, names as ({names_sql(t)}),
m as (select p.dep, min(p.ref) m from pairs p join pairs q on p.dep = q.ref and p.ref = q.dep group by p.dep),
c as (select a.attr, least(a.attr, coalesce(m.m, a.attr)) k from names a left join m on m.dep = a.attr),
e as (select distinct x.k dep, y.k ref from pairs p join c x on x.attr = p.dep join c y on y.attr = p.ref where x.k <> y.k),
f as (select * from e except select a.dep, b.ref from e a join e b on a.ref = b.dep)
select d.t dep_table, d.c dep_cols, r.t ref_table, r.c ref_cols, 1 arity from f join names d on d.attr = f.dep join names r on r.attr = f.ref"""


def declared_sql() -> str:
    parts = []
    for d, dc, r, rc in DECLARED:
        left = f"select distinct {', '.join(f'{c}::varchar' for c in dc)} from {d}"
        right = f"select distinct {', '.join(f'{c}::varchar' for c in rc)} from {r}"
        parts.append(f"""select '{d}' dep_table, '{",".join(dc)}' dep_cols, '{r}' ref_table, '{",".join(rc)}' ref_cols,
(select count(*) from ({left})) dep_distinct, (select count(*) from ({left} except {right})) missing""")
    return f"select *, missing = 0 holds, missing::double / dep_distinct error from ({' union all '.join(parts)})"


def md5_hash(c: str) -> str:
    return f"('0x' || substr(md5(coalesce('v' || \"{c}\"::varchar, 'n')), 1, 15))::bigint"


def fold60(hashes: list[str]) -> str:
    acc = hashes[0]
    for h in hashes[1:]:
        acc = f"xor((({acc} & 576460752303423487) << 1) | ({acc} >> 59), {h})"
    return acc


def hashed_sql(table: str) -> str:
    return f"select {', '.join(f'{md5_hash(c)} h{k}' for k, c in enumerate(COLUMNS[table].split()))} from {table}"


def sample_sql(table: str, n: int, p: str = "") -> str:
    """CTEs ending in {p}sample(h0, ...)."""
    cols = [f"h{k}" for k in range(len(COLUMNS[table].split()))]
    all_ = ", ".join(cols)
    one = " union ".join(f"(select {all_} from (select *, row_number() over (partition by {c} order by o, {all_}) k from {p}r) where k = 1 order by {c} limit {n})" for c in cols)
    return f"{p}h as materialized ({hashed_sql(table)}), {p}r as materialized (select *, {fold60(cols)} o from {p}h), {p}sample as ({one})"


def filled_ctes(n: int) -> str:
    """CTEs ending in cells(combo, h), the core tables' distinct hashes, and keys(h), those of samples of ``n``."""
    core = tables(CORE)
    combo = {(name, c): k for k, name, _, c in numbered(core)}
    places = [(f"{name}_", name, k, combo[name, c]) for name in core for k, c in enumerate(core[name][1])]
    samples = ", ".join(sample_sql(name, n, f"{name}_") for name in core)
    keys = " union ".join(f"select h{k} h from {p}sample" for p, _, k, _ in places)
    cells = " union ".join(f"select {a} combo, h{k} h from {p}h" for p, _, k, a in places)
    return f"{samples}, keys as materialized ({keys}), cells as materialized ({cells})"


def filled_sql(n: int, lgk: int) -> str:
    return f"""with {filled_ctes(n)}, names as ({names_sql(tables(CORE))}),
miss as (select combo, h & {(1 << lgk) - 1} b, h >> {lgk} x from cells where h not in (select h from keys)),
regs as (select combo, b, max(case when x = 0 then {60 - lgk + 1} else bit_count((x & -x) - 1) + 1 end)::bigint rho from miss group by combo, b),
hits as (select combo, count(*) n from cells where h in (select h from keys) group by combo),
sums as (select combo, count(*) n, sum(rho)::bigint s from regs group by combo)
select t table_name, c column_name, coalesce(hits.n, 0) n_keys, coalesce(sums.n, 0) n_registers, coalesce(sums.s, 0) rho_sum
from names left join hits on hits.combo = attr left join sums on sums.combo = attr"""


def filled_sets_sql(n: int) -> str:
    return f"""with {filled_ctes(n)}, s as (select h, list_sort(list(combo)) m from cells where h in (select h from keys) group by h)
select array_to_string(m, ',') members, count(*) n_values from s group by m"""


def estimates_sql(lgk: int) -> str:
    core, m = tables(CORE), float(1 << lgk)
    cells = " union all ".join(f"select {k} combo, {md5_hash(c)} h from {rel}" for k, _, rel, c in numbered(core))
    return f"""with cells as ({cells}), names as ({names_sql(core)}),
regs as (select combo, h & {(1 << lgk) - 1} b, max(case when h >> {lgk} = 0 then {60 - lgk + 1} else bit_count(((h >> {lgk}) & -(h >> {lgk})) - 1) + 1 end) rho from cells group by 1, 2),
e as (select combo, {m} - count(*) zero, {0.7213 / (1 + 1.079 / m) * m * m!r} / (sum(pow(2.0, -rho)) + {m} - count(*)) raw from regs group by combo)
select t table_name, c column_name, round(case when raw <= {2.5 * m} and zero > 0 then {m} * ln({m} / zero) else raw end, 3) estimate from e join names on attr = combo"""


def registers_sql(table: str, lgk: int) -> str:
    parts = []
    for k in range(len(COLUMNS[table].split())):
        parts.append(f"select {k} combo, (h{k} & {(1 << lgk) - 1})::int bucket, h{k} >> {lgk} x from h")
    return f"""with h as ({hashed_sql(table)}), c as ({' union all '.join(parts)})
select combo, bucket, max(case when x = 0 then {60 - lgk + 1} else bit_count((x & -x) - 1) + 1 end)::int rho from c group by combo, bucket"""


SPARSE: Tables = {
    "a": ("(select o_orderkey k, case when o_orderkey % 3 = 0 then o_custkey end c, case when o_orderkey % 5 = 0 then o_orderstatus end s, case when o_orderkey % 7 = 0 then o_orderpriority end p, null::varchar z from orders)", ["k", "c", "s", "p", "z"]),
    "b": ("(select o_orderkey k2, case when o_orderkey % 2 = 0 then o_custkey end c2, o_orderstatus s2, case when o_orderkey % 2 = 0 then o_orderpriority end p2, case when o_orderkey % 11 = 0 then o_orderstatus end z2 from orders)", ["k2", "c2", "s2", "p2", "z2"]),
}
HIGH: Tables = {
    "dep": (f"(select {', '.join(HIGH_ARITY)} from lineitem join part on l_partkey = p_partkey where p_brand = '{BRAND}')", list(HIGH_ARITY)),
    "ref": (f"(select {', '.join(f'{c} {n}' for c, n in zip(HIGH_ARITY, 'osedtfh', strict=True))} from lineitem)", list("osedtfh")),
}
EXAMPLE: Tables = {
    "people": ("(select 'P' || o_orderkey uid, o_orderpriority as name, o_custkey dln from orders)", ["uid", "name", "dln"]),
    "licences": ("(select c_custkey dlid, c_mktsegment country from customer where c_custkey in (select o_custkey from orders))", ["dlid", "country"]),
}
STREAM: Tables = {"customer": ("customer", ["c_custkey"]), "events": ("events", COLUMNS["events"].split())}


def wide_tables(width: int) -> Tables:
    return {"residues": ("(select " + ", ".join(f"event_id % {2 + j} m{j:03d}" for j in range(width)) + " from events)", [f"m{j:03d}" for j in range(width)])}


def type_where() -> str:
    """Pairs of one type class, as a condition on names d and r."""
    classes = {c: "fractional" for c in TYPES["double"].split()} | {c: "timestamp" for c in TYPES["timestamp"].split()} | {c: "string" for c in TEXT.split()}
    case = lambda x: f"case {' '.join(f'when {x}.c in ({chr(44).join(chr(39) + c + chr(39) for c, k in classes.items() if k == kind)}) then {chr(39)}{kind}{chr(39)}' for kind in ('fractional', 'timestamp', 'string'))} else 'integer' end"
    return f"{case('d')} = {case('r')}"


def oracle_sql() -> dict[str, str]:
    core, every, prose = tables(CORE), tables(CORE + EXTRA), tables(PROSE)
    unary_core, dedupe = unary_sql(core), dedupe_sql(core)
    count = filled_sql(500, 21)
    orders = COLUMNS["orders"].split()
    return {
        "exact_unary_core": unary_core,
        "exact_unary_all": unary_sql(every),
        "exact_unary_typed": unary_sql(core, type_where()),
        "exact_unary_maxpruned": unary_core,
        "exact_unary_merge_engine": unary_core,
        **{f"dedupe_{k}": dedupe for k in ("column_scan", "set", "sort", "view", "pair", "chunked", "set_single", "auto")},
        **{f"exact_unary_merge_{k}": unary_core for k in ("baseline", "set_single", "auto")},
        "inverted_index_sets": sets_sql(core),
        "inverted_unary": unary_core,
        "pairwise_unary": unary_core,
        "pairwise_joined_unary": unary_core,
        "attr_stats": stats_sql(every),
        "dataset_profile": profile_sql({n: (t, most_columns(t)) for n, t in (("core", core), ("all", every), ("prose", prose), ("sparse", SPARSE), ("high_arity", HIGH))} | {"wide": (wide_tables(64), 1)}),
        "level_counts": level_counts_sql({n: (t, most_columns(t)) for n, t in (("core", core), ("sparse", SPARSE), ("high_arity", HIGH))}),
        "explosion_guard": guard_sql(32),
        "index_lookups": lookups_sql(core),
        "exact_nary_high_arity": nary_sql(HIGH, 7),
        "sketch_nary_high_arity": nary_sql(HIGH, 7),
        "sketch_unary_hll_only": unary_core,
        "sketch_estimates": estimates_sql(12),
        "exact_nary_core": binary_sql(core),
        "exact_nary_sparse": binary_sql(SPARSE),
        "lattice_candidates_2": candidates2_sql(core),
        "sketch_unary_default": unary_core,
        "sketch_unary_verified": unary_core,
        "sketch_unary_index_only": unary_core,
        "sketch_unary_sets": unary_core,
        "sketch_registers_md5": registers_sql("orders", 8),
        "sketch_sample_md5": f"with {sample_sql('orders', 50)} select {', '.join(f'h{k} {c}' for k, c in enumerate(orders))} from sample",
        "sketch_index_keys_md5": f"with {sample_sql('orders', 50)} " + " union ".join(f"select h{k} h from sample" for k in range(len(orders))),
        "combined_hash_md5": f"select {fold60([md5_hash(c) for c in ('l_orderkey', 'l_linenumber', 'l_shipdate')])} h, count(*) n from lineitem group by 1",
        **{f"fill_{k}": count for k in ("row", "htab", "batch", "vector", "sql")},
        "fill_sets": filled_sets_sql(500),
        "fill_bits": filled_sets_sql(500),
        "wide_unary": unary_sql(wide_tables(64)),
        # by the closed form, since the tables have more rows than columns here: masks of 259 columns take minutes
        "wide_unary_259": "select 'residues' dep_table, format('m{:03d}', d.i) dep_cols, 'residues' ref_table, format('m{:03d}', r.i) ref_cols, 1 arity from range(259) d(i), range(259) r(i) where d.i < r.i",
        "prose_unary": unary_sql(prose),
        "worked_example": unary_sql(EXAMPLE),
        "partial_inds": partial_sql(core, 0.1),
        "validate_declared": declared_sql(),
        "violations": "select distinct o_orderkey::varchar c0 from orders except select l_orderkey::varchar from lineitem",
        "fk_candidates": fk_sql(core),
        "ind_classes": classes_sql(every),
        "ind_reduced": reduced_sql(every),
        "join_suggestion": "select c_mktsegment, count(*) n, count(distinct o_orderkey) orders from orders join customer on o_custkey = c_custkey group by 1",
        "ind_totals": f"with i as ({unary_core}) select dep_table, arity, count(*) n from i group by rollup (dep_table, arity)",
        "events_incremental_inds": unary_sql(STREAM),
    }
