"""SQL for DuckDB that says what the queries must return, from the sets themselves and bit by bit."""

from __future__ import annotations

from filterfleet.functions.params import FilterSpec
from filterfleet.sources.collections import ABSENT

MEMBERS = {
    "block100": "select distinct o_orderkey // 100 as site_id, o_orderkey as element from orders",
    "block1000": "select distinct o_orderkey // 1000 as site_id, o_orderkey as element from orders",
    "block10": "select distinct o_orderkey // 10 as site_id, o_orderkey as element from orders",
    "cust": "select distinct o_custkey as site_id, o_orderkey as element from orders",
    "part": "select distinct l_partkey as site_id, l_orderkey as element from lineitem",
    "supp": "select distinct l_suppkey as site_id, l_partkey as element from lineitem",
    "order": "select distinct l_orderkey as site_id, l_partkey as element from lineitem",
    "user": "select distinct user_id as site_id, event_id as element from events",
    "day": "select distinct date_diff('day', date '2024-01-01', ts::date) as site_id, user_id as element from events",
    "nation": "select distinct c_nationkey::bigint as site_id, c_custkey as element from customer",
    "source": "select distinct substr(source, 4, 9)::bigint as site_id, ('0x' || substr(md5(text), 1, 15))::bigint as element from documents",
    "supnat": "select distinct s_nationkey::bigint as site_id, l_orderkey as element from lineitem join supplier on l_suppkey = s_suppkey",
    "host": "select distinct ('0x' || substr(md5(regexp_extract(url, '^[a-z]+://([^/]+)', 1)), 1, 15))::bigint as site_id, ('0x' || substr(md5(url), 1, 15))::bigint as element from pages",
    "doc": r"select doc_id as site_id, ('0x' || substr(md5(w), 1, 15))::bigint as element from (select distinct doc_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}0-9]+')) as w from documents) where w <> ''",
    "conv": r"select conv_id as site_id, ('0x' || substr(md5(w), 1, 15))::bigint as element from (select distinct conv_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}0-9]+')) as w from conversations) where w <> ''",
}

BIT = "case when {p} % 64 = 63 then (-9223372036854775808)::bigint else 1::bigint << ({p} % 64)::int end"


def positions(source: str, keep: str, spec: FilterSpec) -> str:
    """keep, pos for every element and hash function of `source`."""
    if spec.family == "linear_odd":
        seeds = ", ".join(f"{a % spec.m}::bigint" for a in spec.seeds)
        return f"select {keep}, (a * (((element % {spec.m}) + {spec.m}) % {spec.m})) % {spec.m} as pos from {source}, (select unnest([{seeds}]) as a)"
    half = lambda at: f"('0x' || substr(md5(element::varchar), {at}, 15))::bigint % {spec.m}"
    return f"select {keep}, ({half(1)} + i * ({half(17)})) % {spec.m} as pos from {source}, (select unnest(range({spec.k})) as i)"


def chain(*parts: tuple[str, str], then: str) -> str:
    return "with recursive " + ",\n".join(f"{name} as ({sql})" for name, sql in parts) + "\n" + then


def members(name: str) -> tuple[str, str]:
    return "mem", MEMBERS[name]


def bits(spec: FilterSpec, of: str = "mem", name: str = "bits") -> tuple[str, str]:
    return name, f"select distinct filter_id, pos from ({positions(of, 'site_id as filter_id', spec)})"


def words(of: str = "bits", name: str = "words", keys: str = "filter_id") -> tuple[str, str]:
    return name, f"select {keys}, pos // 64 as word_ix, bit_or({BIT.format(p='pos')}) as word from {of} group by {keys}, pos // 64"


def probes(every: int = 100, of: str = "mem") -> tuple[str, str]:
    there = f"select distinct element from {of} where element % {every} = 0"
    return "probes", f"select element * 2 as query_id, element, 'present' as kind from ({there}) union all select element * 2 + 1, element + {ABSENT}, 'absent' from ({there})"


def probe_bits(spec: FilterSpec) -> tuple[str, str]:
    return "pb", f"select query_id, pos, count(*) over (partition by query_id) as kd from (select distinct query_id, pos from ({positions('probes', 'query_id', spec)}))"


def matches(of: str = "bits") -> tuple[str, str]:
    return "matches", f"select query_id, filter_id from pb join {of} using (pos) group by query_id, filter_id having count(*) = any_value(kd)"


def search(name: str, spec: FilterSpec, every: int = 100, where: str = "") -> list[tuple[str, str]]:
    left = ("kept", f"select * from bits {where}") if where else ("kept", "select * from bits")
    return [members(name), bits(spec), left, probes(every), probe_bits(spec), matches("kept")]


def sizes(d: int, of: str = "mem", site: str = "site_id") -> list[tuple[str, str]]:
    """lv (level, n): level sizes of a sorted load; anc (filter_id, level, ix): every filter's ancestors."""
    return [
        ("leaves", f"select site_id as filter_id, row_number() over (order by {site}) - 1 as place from (select distinct site_id from {of})"),
        ("lv", f"select 0 as level, count(*) as n from leaves union all select level + 1, case when n <= {2 * d} then 1 else (n - {d}) // {d + 1} + 1 end from lv where n > 1 or level = 0"),
        ("anc", f"select filter_id, 0 as level, place as ix from leaves union all select filter_id, anc.level + 1, least(ix // {d + 1}, lv.n - 1) from anc join lv on lv.level = anc.level + 1"),
        ("nodes", "select level, ix, (ix + coalesce((select sum(n) from lv b where b.level < g.level), 0))::bigint as node_id from (select distinct level, ix from anc) g"),
    ]


def edges(d: int) -> tuple[str, str]:
    """shape (level, ix, node_id, parent_id, n_children)."""
    kids = "select level + 1 as level, p as ix, count(*) as n_children from (select nodes.level, nodes.ix, least(nodes.ix // {e}, up.n - 1) as p from nodes join lv up on up.level = nodes.level + 1) group by 1, 2".format(e=d + 1)
    return "shape", f"select nodes.level, nodes.ix, nodes.node_id, (select u.node_id from nodes u join lv up on up.level = u.level where u.level = nodes.level + 1 and u.ix = least(nodes.ix // {d + 1}, up.n - 1)) as parent_id, coalesce(k.n_children, 0) as n_children from nodes left join ({kids}) k on k.level = nodes.level and k.ix = nodes.ix"


NODE_BITS = ("nbits", "select distinct anc.level, anc.ix, bits.pos from bits join anc using (filter_id)")
NODE_HITS = ("hits", "select query_id, level, ix from pb join nbits using (pos) group by query_id, level, ix having count(*) = any_value(kd)")
