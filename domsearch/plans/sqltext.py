"""DuckDB text of the corpora, sketches and searches, from which oracles are put together."""

from __future__ import annotations

from ..functions.hashing import PRIME, coefficients
from ..functions.tuning import RATIO_EDGES, precompute
from ..operators.extract import COLUMN_TABLES

# fixed values: the scalar columns of the given tables, by table; d marks doubles, t times
COLUMNS = {
    "region": "r_regionkey r_name", "nation": "n_nationkey n_name n_regionkey", "customer": "c_custkey c_name c_nationkey c_acctbal:d c_mktsegment",
    "supplier": "s_suppkey s_name s_nationkey s_acctbal:d", "part": "p_partkey p_name p_brand p_type p_size p_retailprice:d",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice:d o_orderdate:t o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity:d l_extendedprice:d l_discount:d l_tax:d l_returnflag l_linestatus l_shipdate:t",
    "events": "event_id ts:t user_id event_type value:d props", "documents": "doc_id text lang source n_chars", "pages": "page_id url html",
    "benchmark": "item_id text", "conversations": "conv_id turn role text",
}


def _columns(tables=COLUMN_TABLES) -> str:
    parts = []
    for name in tables:
        for c in COLUMNS[name].split():
            c, _, kind = c.partition(":")
            value = {"d": f"cast(cast(round({c} * 100) as bigint) as varchar)", "t": f"strftime({c}, '%Y-%m-%d %H:%M:%S')"}.get(kind, f"cast({c} as varchar)")
            parts.append(f"select '{name}.{c}' domain_id, {value} as value from {name}")
    return " union ".join(parts)


def _dated(prefix: str, date: str, value: str, source: str, grains: str) -> str:
    return " union all ".join(f"select '{prefix}:{g}:' || strftime(date_trunc('{g}', {date}), '%Y-%m-%d') domain_id, cast({value} as varchar) as value from {source}" for g in grains.split())


def _slices() -> str:
    return "select distinct domain_id, value from (" + " union all ".join([
        _dated("li.part", "l_shipdate", "l_partkey", "lineitem", "day week month quarter year"),
        _dated("o.cust", "o_orderdate", "o_custkey", "orders", "day month quarter year"),
        "select 'part_by_supp:' || l_suppkey, cast(l_partkey as varchar) from lineitem",
        "select 'part_by_cust:' || o_custkey, cast(l_partkey as varchar) from lineitem join orders on l_orderkey = o_orderkey",
    ]) + ")"


def _text() -> str:
    words = r"unnest(string_split_regex(lower({0}), '\s+'))"
    tokens = words.format("text")
    return "select distinct domain_id, value from (" + " union all ".join([
        *(f"select {label} domain_id, {tokens} as value from documents" for label in ("'doc:' || doc_id", "'src:' || source || ':' || lang", "'lang:' || lang", "'all:documents'")),
        f"select 'conv:' || conv_id, {tokens} from conversations",
        "select 'page:' || page_id, " + words.format("regexp_replace(html, '<[^>]*>', ' ', 'g')") + " from pages",
    ]) + ") where value <> ''"


CORPUS = {"columns": f"select domain_id, value from ({_columns()}) where value is not null and value <> ''", "slices": _slices(), "text": _text()}
_TOKENS = r"select distinct '{0}:' || {0}_id domain_id, unnest(string_split_regex(lower(text), '\s+')) as value from {1}"
CORPUS["documents"] = f"select * from ({_TOKENS.format('doc', 'documents')}) where value <> ''"
CORPUS["documents and items"] = f"select * from ({_TOKENS.format('doc', 'documents')} union all {_TOKENS.format('item', 'benchmark')}) where value <> ''"


def columns_of(tables: list[str]) -> str:
    """Domains of the scalar columns of some tables."""
    return f"select domain_id, value from ({_columns(tables)}) where value is not null and value <> ''"


def doubles(values) -> str:
    return ", ".join(f"({x!r}::double)" for x in values)


def ratio_bin(u: str, q: str) -> str:
    return "(" + " + ".join(f"(case when {u}::double / {q} >= {e!r}::double then 1 else 0 end)" for e in RATIO_EDGES[1:]) + ")"


def equi_depth(n: int, hist: str = "hist") -> str:
    return f"select size, n_domains, cum_before, cast(least({n} - 1, ({n} * cum_before) // (select sum(n_domains) from {hist})) as integer) part_id from {hist}"


META = "select part_id, size_lo, coalesce(lead(size_lo) over (order by part_id), size_max + 1) size_hi_excl, size_max, n_domains from (select part_id, min(size) size_lo, max(size) size_max, cast(sum(n_domains) as bigint) n_domains from {0} group by 1)"


def sketches(corpus: str = "slices", m: int = 64, seed: int = 1, keep: str = "true", min_size: int = 10) -> list[str]:
    fam = ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(coefficients(m, seed)))
    return [
        f"ent0 as materialized ({CORPUS[corpus]})",
        f"dom as materialized (select domain_id, count(*) size from ent0 where {keep} group by 1 having count(*) >= {min_size})",
        "ent as materialized (select domain_id, value from ent0 semi join dom using (domain_id))",
        f"hashed as (select domain_id, cast('0x' || substr(md5(value), 1, 15) as bigint) % {PRIME} h from ent)",
        f"fam(i, a, b) as (values {fam})",
        f"sig as materialized (select domain_id, i, min((a * h + b) % {PRIME}) v from hashed, fam group by 1, 2)",
    ]


def histogram() -> list[str]:
    return ["hist as (select size, n_domains, cast(coalesce(sum(n_domains) over (order by size rows between unbounded preceding and 1 preceding), 0) as bigint) cum_before from (select size, count(*) n_domains from dom group by 1))"]


def index(n: int) -> list[str]:
    return [*histogram(), f"placed as ({equi_depth(n)})", f"meta as ({META.format('placed')})", "idx as (select domain_id, size, part_id from dom join placed using (size))"]


ASKED = "cast('0x' || substr(md5(domain_id), 1, 15) as bigint) % 20 = 0"


def sample(k: int | None = None, where: str = "true") -> list[str]:
    """Every domain whose portable hash is divisible by 20, or the first k by md5."""
    if k is None:
        return [f"qs as (select domain_id query_id, size q from dom where {where} and {ASKED})"]
    return [f"qs as (select domain_id query_id, size q from dom where {where} order by md5(domain_id), domain_id limit {k})"]


def truth() -> list[str]:
    return [
        "asked_values as (select query_id, q, value from qs join ent on query_id = domain_id)",
        "pairs as materialized (select query_id, q, domain_id, size x, overlap from (select query_id, q, domain_id, count(*) overlap from asked_values join ent using (value) group by 1, 2, 3) join dom using (domain_id))",
    ]


def candidates(m: int, thresholds: list[float], prune: bool = True, layout="free") -> list[str]:
    """Search of the queries ``qs`` over ``sig``, ``idx`` and ``meta``; a layout of trees cuts bands at its depth."""
    rows = ", ".join(f"({k}, {t!r}::double, {b}, {r})" for k, _, t, b, r, _, _ in precompute(m, thresholds, layout=layout))
    band, held = ("i // r", "i < most * r") if layout == "free" else (f"i // {layout[1]}", f"i % {layout[1]} < r and i // {layout[1]} < most")
    own = "i < (i // r + 1) * r" if layout == "free" else f"i % {layout[1]} < r"
    return [
        f"tun(ratio_bin, t_star, b, r) as (values {rows})",
        f"bins as (select query_id, q, part_id, size_max, {ratio_bin('size_max', 'q')} ratio_bin from qs, meta)",
        "plan as (select query_id, q, t_star, part_id, size_max, b, r from bins join tun using (ratio_bin)" + (" where size_max::double / q >= t_star)" if prune else ")"),
        "shapes as (select part_id, r, max(b) most from plan group by 1, 2)",
        f"held as materialized (select domain_id, part_id, r, {band} band, string_agg(cast(v as varchar), '-' order by i) bucket from sig join idx using (domain_id) join shapes using (part_id) where {held} group by 1, 2, 3, 4)",
        f"own as (select domain_id query_id, r, {band} band, string_agg(cast(v as varchar), '-' order by i) bucket from sig join (select distinct query_id, r from plan) p on domain_id = p.query_id where {own} group by 1, 2, 3)",
        "found as materialized (select distinct p.query_id, p.t_star, h.domain_id from plan p join own o on o.query_id = p.query_id and o.r = p.r and o.band < p.b join held h on h.part_id = p.part_id and h.r = p.r and h.band = o.band and h.bucket = o.bucket)",
    ]


def sql(ctes: list[str], select: str) -> str:
    return "with " + ",\n".join(ctes) + "\n" + select
