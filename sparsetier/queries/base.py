"""The registry, and the tables and SQL fragments that queries share."""

from __future__ import annotations

from sparsetier.sources import matrices as S

_Q, _SQL = {}, {}

OP = "op as (select l_orderkey i, l_partkey j, cast(sum(l_quantity) as bigint) v from lineitem where l_orderkey is not null and l_partkey is not null group by 1, 2)"
PS = "ps as (select l_partkey i, l_suppkey j, cast(sum(l_quantity) as bigint) v from lineitem group by 1, 2)"
PP = ("pp as (select a i, b j, count(*) v from (select l_partkey a, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey) b "
      "from lineitem) where b is not null group by 1, 2)")
UU = ("uu as (select a i, b j, count(*) v from (select user_id a, lead(user_id) over (partition by date_trunc('hour', ts) order by ts, event_id) b from events) "
      "where a is not null and b is not null group by 1, 2)")
COP = f"with {OP}, c as (select a.j i, b.j j, cast(sum(a.v * b.v) as bigint) v from op a join op b on a.i = b.i group by 1, 2) "
SQUARE = f"with {PP}, c as (select a.i i, b.j j, cast(sum(a.v * b.v) as bigint) v from pp a join pp b on a.j = b.i group by 1, 2) "
USQUARE = f"with {UU}, c as (select a.i i, b.j j, cast(sum(a.v * b.v) as bigint) v from uu a join uu b on a.j = b.i group by 1, 2) "
INTER = f"with {OP}, x as (select a.j i, b.j j, a.i k, a.v * b.v p from op a join op b on a.i = b.i) "


def portable_hash_sql(x: str, seed: int) -> str:
    a = f"(((({x}) % 2147483647) * 48271 + {seed}) % 2147483647)"
    b = f"(({a} * {a} + ({x})) % 2147483647)"
    c = f"(({b} * 69621 + 7) % 2147483647)"
    return f"(({c} * {c} + ({x})) % 2147483647)"


def add(name, query, sql=None):
    _Q[name] = query
    if sql:
        _SQL[name] = sql


def table(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


def pair(spark, d):
    """Part x order and order x part: their product is co-purchase."""
    op = S.order_part(spark, d)
    return op.transpose(), op


def queries():
    return dict(_Q)


def oracle_sql():
    return dict(_SQL)
