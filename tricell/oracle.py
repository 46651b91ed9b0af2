"""SQL of the same graphs and measures for an independent engine (DuckDB's dialect)."""

from __future__ import annotations

from .functions.colours import PRIME, coefficients


def _dictionary(name: str, rows: str, column: str) -> str:
    return f"{name} as (select name, row_number() over (order by name) - 1 as id from (select distinct {column} as name from ({rows})) where name is not null)"


def _sides(x: str, y: str, z: str, rows: str) -> str:
    a, b, c = f"{x} * 3", f"{y} * 3 + 1", f"{z} * 3 + 2"
    return f"p as (select distinct u, v from (select {a} as u, {b} as v from {rows} union all select {b}, {c} from {rows} union all select {a}, {c} from {rows}))"


def _together(rows: str, key: str, member: str) -> str:
    keys = key.split(", ")
    on = " and ".join(f"x.{k} = y.{k}" for k in keys)
    return f"m as (select distinct {key}, {member} as m from ({rows}) where {member} is not null), p as (select distinct x.m as u, y.m as v from m x join m y on {on} and x.m < y.m)"


_CPS = "select distinct o_custkey, l_partkey, l_suppkey from lineitem join orders on l_orderkey = o_orderkey"
_SELLS = "select distinct l_suppkey, p_brand, p_type from lineitem join part on l_partkey = p_partkey"
_SLICE = _SELLS + " where l_returnflag = 'R' and l_quantity >= 45"
_CBT = "select distinct o_custkey, p_brand, p_type from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey where l_returnflag = 'R'"
_UTK = "select distinct user_id, event_type, cast(json_extract_string(props, '$.k') as bigint) as k from events"
_LINES = "select doc_id, trim(line) as line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(trim(line)) >= 20"
_HREFS = "select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages"
_CONV = "select distinct conv_id, turn, role from conversations"


def _brand_type(rows: str, first: str) -> str:
    return (
        f"r0 as ({rows}), {_dictionary('db', 'select * from r0', 'p_brand')}, {_dictionary('dt', 'select * from r0', 'p_type')}, "
        f"r as (select {first} as x, db.id as y, dt.id as z from r0 join db on db.name = p_brand join dt on dt.name = p_type), {_sides('x', 'y', 'z', 'r')}"
    )


#: For each graph, common table expressions that end in p(u, v).
PAIRS = {
    "copurchase": _together("select l_orderkey, l_partkey from lineitem", "l_orderkey", "l_partkey"),
    "cps": f"r as ({_CPS}), {_sides('o_custkey', 'l_partkey', 'l_suppkey', 'r')}",
    "sells": _brand_type(_SELLS, "l_suppkey"),
    "sells_slice": _brand_type(_SLICE, "l_suppkey"),
    "hub": f"r as (select distinct l_orderkey as x, ascii(l_returnflag) as y, ascii(l_linestatus) as z from lineitem), {_sides('x', 'y', 'z', 'r')}",
    "cbt": _brand_type(_CBT, "o_custkey"),
    "utk": f"r0 as ({_UTK}), {_dictionary('dt', 'select * from r0', 'event_type')}, r as (select user_id as x, dt.id as y, k as z from r0 join dt on dt.name = event_type), {_sides('x', 'y', 'z', 'r')}",
    "coact": _together("select event_type, floor(epoch(ts) / 600) as bucket, user_id from events", "event_type, bucket", "user_id"),
    "nation": _together("select c_nationkey, c_custkey from customer", "c_nationkey", "c_custkey"),
    "cosupply": _together("select l_orderkey, l_suppkey from lineitem", "l_orderkey", "l_suppkey"),
    "docline": _together(_LINES, "line", "doc_id"),
    "pages": _together(_HREFS, "href", "page_id"),
    "links": f"h as (select distinct page_id, href from ({_HREFS})), {_dictionary('dl', 'select * from h', 'href')}, " + _together("select page_id, dl.id as link from h join dl on dl.name = href", "page_id", "link"),
    "vec": "ev as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings), p as (select x.vec_id as u, y.vec_id as v from ev x join ev y on x.vec_id < y.vec_id where round(list_cosine_similarity(x.e, y.e), 6) >= 0.3)",
    "conv": f"r0 as ({_CONV}), {_dictionary('dr', 'select * from r0', 'role')}, r as (select conv_id as x, turn as y, dr.id as z from r0 join dr on dr.name = role), {_sides('x', 'y', 'z', 'r')}",
    "bip": "p as (select o_custkey * 2 as u, o_orderkey * 2 + 1 as v from orders)",
    "labelled_docs": _together(f"select * from ({_LINES}) where doc_id in (select doc_id from labels where quality = 1)", "line", "doc_id"),
    "bench_docs": _together("select item_id, word from (select item_id, unnest(regexp_split_to_array(lower(text), '\\W+')) as word from benchmark) where length(word) >= 8", "word", "item_id"),
}

#: From p: canonical edges e, degrees d, oriented edges o, triangles t.
GRAPH = """
e as (select distinct least(u, v)::bigint as u, greatest(u, v)::bigint as v from p where u <> v),
d as (select id, count(*) as deg from (select u as id from e union all select v from e) group by id),
o as materialized (select case when (du.deg, u) < (dv.deg, v) then u else v end as lo, case when (du.deg, u) < (dv.deg, v) then v else u end as hi,
    least(du.deg, dv.deg) as deg_lo, greatest(du.deg, dv.deg) as deg_hi from e join d du on du.id = u join d dv on dv.id = v)"""
#: the paths first, then their closing edges: left to itself the engine may close pairs that no path joins
TRIANGLES = """
paths as materialized (select x.lo as a, x.hi as b, y.hi as c from o x join o y on y.lo = x.hi),
t as (select a, b, c from paths semi join o z on z.lo = paths.a and z.hi = paths.c)"""


def edges(graph: str, tail: str, extra: str = "") -> str:
    """`tail` over e, d and o of a graph."""
    return f"with {PAIRS[graph]}, {GRAPH}{', ' + extra if extra else ''} {tail}"


def triangles(graph: str, tail: str = "select a, b, c from t", extra: str = "") -> str:
    """`tail` over t, besides e, d and o."""
    return edges(graph, tail, f"{TRIANGLES}{', ' + extra if extra else ''}")


def poly(x: str, ks: list[int]) -> str:
    h = f"{ks[0]}::hugeint"
    for k in ks[1:]:
        h = f"(({h} * {x} + {k}) % {PRIME})"
    return h


def colour(x: str, c: int, seed: int) -> str:
    return "1" if c == 1 else f"cast({poly(x, coefficients(seed))} % {c} + 1 as integer)"


def field_times(x: str, y: str, m: int, modulus: int) -> str:
    """Product in the field of 2^m elements: shifted copies, then the modulus taken off from the top bit down."""
    product = f"list_reduce(list_transform(range(0, {m}), lambda i: case when ({y} >> i) & 1 = 1 then {x} << i else 0::bigint end), lambda p, q: xor(p, q))"
    return f"list_reduce(list_concat([{product}], range({2 * m - 2}, {m - 1}, -1)), lambda v, k: case when (v >> k) & 1 = 1 then xor(v, {modulus}::bigint << (k - {m})) else v end)"


def small_bias_rows(m: int, modulus: int, masks: list[int], ranks: str) -> str:
    """rank and the bits b0, b1, ... of members given by their masks over (1, x, x^3)."""
    bits = ", ".join(f"cast(bit_count({mask}::bigint & y) & 1 as integer) as b{i}" for i, mask in enumerate(masks))
    square = f"select rank, {field_times('rank', 'rank', m, modulus)} as sq from {ranks}"
    cube = f"select rank, {field_times('sq', 'rank', m, modulus)} as cu from ({square})"
    return f"select rank, {bits} from (select rank, 1 | (rank << 1) | (cu << {m + 1}) as y from ({cube}))"


def bit(x: str, level: int, seed: int) -> str:
    return f"({poly(x, coefficients(seed, level=level))} % 2)"


def refined(x: str, level: int, seed: int) -> str:
    z = "1"
    for i in range(1, level + 1):
        z = f"(2 * {z} - {bit(x, i, seed)})"
    return f"cast({z} as integer)"
