"""DuckDB SQL of the mining queries: power sets of the frequent items, matched against distinct rows."""

from __future__ import annotations

from ..sources.databases import COUNT_SQL, LONG_SQL


def base(db: str, theta: float | int | None = None, long_sql: str | None = None, rows: int | None = None) -> str:
    """CTEs ``tx, m, ms, fi(item, id, c), g(mask, w)``, of frequent items only if a threshold is given."""
    count = f"select {rows}" if rows is not None else COUNT_SQL.get(db, "select count(distinct tid) from tx")
    least = "1" if theta is None else str(theta) if isinstance(theta, int) else f"greatest(1, ceil({theta} * m - 1e-9))::bigint"
    return f"""with tx as ({long_sql or LONG_SQL[db]}), m as (select ({count})::bigint as m), ms as (select {least} as minsup, m from m),
fi as (select item, c, row_number() over (order by item) - 1 as id from (select item, count(*) as c from tx group by item having count(*) >= (select minsup from ms))),
g as (select mask, count(*)::bigint as w from (select tid, sum(1::bigint << id)::bigint as mask from tx join fi using (item) group by tid) group by mask)"""


def frequent(db: str, theta: float | int, long_sql: str | None = None, rows: int | None = None) -> str:
    """And ``ps(s, sup)``, all frequent itemsets, ``up`` and ``mx(s, sup)``, the maximal ones."""
    return base(db, theta, long_sql, rows) + """,
ps as (select s, sum(w)::bigint as sup from (select unnest(range(1::bigint, (select 1::bigint << count(*) from fi))) as s) join g on (g.mask & s) = s group by s having sum(w) >= (select minsup from ms)),
up as (select distinct xor(s, 1::bigint << id) as s from ps join fi on (s >> id) & 1 = 1),
mx as (select * from ps where s not in (select s from up))"""


def named(table: str, extra: str = "") -> str:
    """Rows of a CTE ``(s, sup)`` with item names."""
    return f"""
select string_agg(item, ',' order by item) as itemset, bit_count(s)::int as size, any_value(sup)::bigint as sup, round(any_value(sup) / any_value((select m from m))::double, 6) as freq
from {table} join fi on (s >> id) & 1 = 1 {extra} group by s"""


def frequent_sql(db: str, theta: float | int) -> str:
    return frequent(db, theta) + named("ps")


def maximal_sql(db: str, theta: float | int) -> str:
    return frequent(db, theta) + named("mx")


CLOSED = """,
cu as (select distinct xor(s, 1::bigint << id) as s, sup from ps join fi on (s >> id) & 1 = 1),
cl as (select ps.* from ps anti join cu on ps.s = cu.s and ps.sup = cu.sup)"""


def closed_sql(db: str, theta: float | int) -> str:
    return frequent(db, theta) + CLOSED + named("cl")


INFREQUENT = """,
b as (select s from ps union all select 0::bigint),
cand as (select distinct b.s | (1::bigint << id) as s from b join fi on (b.s >> id) & 1 = 0),
bad as (select distinct c.s from cand c join fi on (c.s >> id) & 1 = 1 where xor(c.s, 1::bigint << id) not in (select s from b)),
mi as (select s from cand where s not in (select s from ps) and s not in (select s from bad)),
rare as (select item from tx group by item having count(*) < (select minsup from ms))"""


def infrequent_sql(db: str, theta: float | int) -> str:
    return frequent(db, theta) + INFREQUENT + """
select string_agg(item, ',' order by item) as itemset, bit_count(s)::int as size from mi join fi on (s >> id) & 1 = 1 group by s
union all select item, 1::int from rare"""


def border_sql(db: str, theta: float | int) -> str:
    return frequent(db, theta) + CLOSED + INFREQUENT + """
select (select count(*) from ps) as n_frequent, (select count(*) from cl) as n_closed, (select count(*) from mx) as n_maximal,
  (select count(*) from mi) + (select count(*) from rare) as n_minimal_infrequent, coalesce((select max(bit_count(s)) from ps), 0)::int as longest"""


def profile_sql(db: str) -> str:
    return base(db) + """
select m, (select count(*) from fi) as n, (select count(*) from g) + case when (select sum(w) from g) < m then 1 else 0 end as distinct_masks,
  round((select sum(c) from fi) / (m * (select count(*) from fi))::double, 6) as density, round((select count(*) from fi) / m::double, 6) as item_ratio from m"""


#: Sizes of the encodings from the matrix: a = absent items of a row, o = ones, n, m.
_SHAPE = """,
per as (select tid, (select count(*) from fi) - count(*) as a from tx group by tid),
sh as (select count(*) as m, (select count(*) from fi) as n, sum(a) as z, (select sum(c) from fi) as o, count(*) filter (a = 1) as one, count(*) filter (a > 0) as lacking, max(a) as la, (select max(c) from fi) as lc from per)"""

_SIZES = {
    "clausal": ("n + m", "z + one", "m - one + 1", "n", "2 * z + z + m + o + n + n", "greatest(la + 1, n, lc + 1)"),
    "reduced": ("n + m", "one", "m - one + 1", "n + lacking", "z + m + z + lacking + o + n + n", "greatest(la + 1, n, lc + 1)"),
    "positive": ("n + m", "0", "1", "m + z + n", "2 * z + z + m + o + n + n", "greatest(la + 1, n, lc + 1)"),
    "dual": ("n + m", "z + one", "m - one + 1", "1", "2 * z + z + m + m + n", "greatest(la + 1, n, m)"),
    "plain": ("n + m", "z + one", "m - one + 1", "1", "2 * z + z + m + m + n", "greatest(la + 1, n, m)"),
    "incremental": ("2 * n + m", "z + one + n", "m - one + 1", "n", "2 * z + z + m + o + n + n + 2 * n", "greatest(la + 1, n, lc + 1)"),
    "fixed": ("2 * n + m + 1", "z + one + n", "m - one + 1", "n + 1", "2 * z + z + m + o + n + n + 2 * n + 2 * n + 1", "greatest(la + 1, n, lc + 1, 2 * n + 1)"),
    "length": ("2 * n + m", "z + one", "m - one + 1", "n + 1", "2 * z + z + m + o + n + n + 2 * n", "greatest(la + 1, 2 * n, lc + 1)"),
    "size": ("n + m", "z + one", "m - one + 1", "n + 1", "2 * z + z + m + o + n + n + n", "greatest(la + 1, n, lc + 1)"),
    "maximality": ("n + m", "z + one", "m - one + 1", "2 * n", "2 * z + z + m + o + n + n + o + n", "greatest(la + 1, n, lc + 1)"),
}


def encoding_size_sql(db: str, kind: str) -> str:
    names = ("variables", "binary", "long", "pb", "literals", "longest")
    return base(db) + _SHAPE + "\nselect " + ", ".join(f"({e})::bigint as {x}" for e, x in zip(_SIZES[kind], names)) + " from sh"


def counts_sql(rows: list[tuple[str, float | int, str]], columns: str = "n_maximal") -> str:
    """(db, theta, config) cells with the number of maximal sets."""
    parts = [f"select '{db}' as db, {theta}::double as theta, '{config}' as config, 'ok' as status, (select count(*) from ({frequent(db, theta)} select * from mx)) as {columns}" for db, theta, config in rows]
    return "\nunion all\n".join(parts)
