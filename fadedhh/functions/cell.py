"""Counter summaries as Spark columns.

A summary is array<struct<n: double, i: bigint>> in ascending order, n being the negated frequency: the natural
order puts the heaviest counter first and breaks ties by item. An absent counter counts as frequency 0. With
two counters this is a sketch cell; with k it is a stream summary.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TYPE = "array<struct<n:double,i:bigint>>"
EMPTY = f"cast(array() as {TYPE})"


def singleton(item: Column, weight: Column) -> Column:
    return F.array(F.struct((-weight).alias("n"), item.cast("long").alias("i")))


def least(cell: Column, k: int = 2) -> Column:
    """Negated smallest frequency: 0 unless all k counters are taken."""
    return F.coalesce(F.get(cell, F.lit(k - 1))["n"], F.lit(0.0))


def combine(a: Column, b: Column, k: int = 2) -> Column:
    """All items of both: sums for shared ones, the other side's minimum added for the rest."""
    ma, mb = least(a, k), least(b, k)
    mine = F.transform(a, lambda u: F.struct((u["n"] + F.coalesce(F.get(F.filter(b, lambda v: v["i"] == u["i"]), F.lit(0))["n"], mb)).alias("n"), u["i"].alias("i")))
    fresh = F.filter(b, lambda v: ~F.exists(a, lambda u: u["i"] == v["i"]))
    return F.concat(mine, F.transform(fresh, lambda v: F.struct((v["n"] + ma).alias("n"), v["i"].alias("i"))))


def purge(cell: Column, k: int = 2) -> Column:
    """The k heaviest counters."""
    return F.slice(F.sort_array(cell), 1, k)


def merge(a: Column, b: Column, k: int = 2) -> Column:
    """Summary of both inputs. For k = 2 the counters sum to the mass of both cells."""
    return purge(combine(a, b, k), k)


def update(cell: Column, item: Column, weight: Column, k: int = 2) -> Column:
    """One occurrence: monitored, free counter and eviction are all the merge with a one-counter summary."""
    return merge(cell, singleton(item, weight), k)


def fold(cells: Column, k: int = 2) -> Column:
    """Merges an array of summaries from left to right."""
    return F.aggregate(cells, F.expr(EMPTY), lambda acc, x: merge(acc, x, k))


def fields(cell: Column) -> list[Column]:
    """i1, f1, i2, f2."""
    out = []
    for j in (0, 1):
        c = F.get(cell, F.lit(j))
        out += [c["i"].alias(f"i{j + 1}"), F.coalesce(-c["n"], F.lit(0.0)).alias(f"f{j + 1}")]
    return out


def from_fields(i1: str = "i1", f1: str = "f1", i2: str = "i2", f2: str = "f2") -> Column:
    both = F.array(*[F.struct((-F.col(f)).alias("n"), F.col(i).alias("i")) for i, f in ((i1, f1), (i2, f2))])
    return F.filter(both, lambda c: c["i"].isNotNull())


def merge_sql(a: str, b: str, k: int = 2) -> str:
    """The merge as DuckDB SQL over lists of {'n', 'i'}."""
    low = lambda x: f"(CASE WHEN len({x}) = {k} THEN {x}[{k}].n ELSE 0.0::DOUBLE END)"
    return (
        f"list_slice(list_sort(list_concat("
        f"list_transform({a}, lambda u: {{'n': u.n + coalesce(list_filter({b}, lambda v: v.i = u.i)[1].n, {low(b)}), 'i': u.i}}), "
        f"list_transform(list_filter({b}, lambda v: NOT list_contains(list_transform({a}, lambda u: u.i), v.i)), lambda v: {{'n': v.n + {low(a)}, 'i': v.i}}))), 1, {k})"
    )
