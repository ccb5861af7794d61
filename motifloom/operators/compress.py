"""Compressed matches: columns v1..vn hold either an id or, for late vertices, an array of ids.

Array columns carry the same name as the vertex they stand for, with prefix c. Constraints between
arrays are left for expansion or counting; all others hold already.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.plans.ir import relation
from motifloom.plans.pattern import QueryGraph


def compare(left: Column, how: str, right: Column) -> Column:
    return {"<": left < right, ">": left > right, "!=": left != right}[how]


def array_vertices(df: DataFrame) -> tuple[int, ...]:
    return tuple(int(c[1:]) for c in df.columns if c[0] == "c" and c[1:].isdigit())


def expand(df: DataFrame, q: QueryGraph, symmetry: bool) -> DataFrame:
    """Plain matches v1..vn: explodes one array after the other and checks it against those before it."""
    placed: list[int] = []
    for x in array_vertices(df):
        checks = [(y, how) for y in placed if (how := relation(q, x, y, symmetry))]
        values = F.col(f"c{x}")
        if checks:
            values = F.filter(values, checker(checks))
        df = df.select(*[c for c in df.columns if c != f"c{x}"], F.explode(values).alias(f"v{x}"))
        placed.append(x)
    return df.select(*[F.col(f"v{v}") for v in q.vertices])


def checker(checks: list[tuple[int, str]]):
    return lambda e: reduce(lambda a, b: a & b, [compare(e, how, F.col(f"v{y}")) for y, how in checks])


def count_column(df: DataFrame, q: QueryGraph, symmetry: bool, same: tuple[frozenset[int], ...] = ()) -> tuple[DataFrame, Column]:
    """A frame and its column with the number of plain matches of each row.

    Arrays without constraints among each other multiply. Two arrays have a closed form; more that
    are the same array by plan (`same`) and all constrained alike have a binomial or falling
    factorial; otherwise all but one of the constrained arrays are expanded first.
    """
    arrays = list(array_vertices(df))
    linked = {x: {x} for x in arrays}
    for x, y in combinations(arrays, 2):
        if relation(q, x, y, symmetry):
            both = linked[x] | linked[y]
            for v in both:
                linked[v] = both
    total = F.lit(1).cast("bigint")
    for group in {frozenset(s) for s in linked.values()}:
        members = sorted(group)
        if len(members) == 1:
            total = total * F.size(f"c{members[0]}")
            continue
        alike = any(group <= s for s in same)
        kinds = {relation(q, x, y, symmetry) for x, y in combinations(members, 2)}
        k, n = len(members), F.size(f"c{members[0]}").cast("bigint")
        if alike and kinds == {"!="}:
            total = total * reduce(lambda a, b: a * b, [F.greatest(n - i, F.lit(0)) for i in range(k)])
        elif alike and kinds in ({"<"}, {">"}, {"<", ">"}):
            total = total * reduce(lambda a, i: F.floor(a * F.greatest(n - i, F.lit(0)) / (i + 1)).cast("bigint"), range(1, k), n)
        elif k == 2 and kinds == {"!="}:
            a, b = (F.col(f"c{m}") for m in members)
            total = total * (F.size(a).cast("bigint") * F.size(b) - F.size(F.array_intersect(a, b)))
        elif k == 2:
            a, b = (f"c{m}" for m in members)
            how = relation(q, members[0], members[1], symmetry)
            total = total * (_below(a, b) if how == "<" else _below(b, a))
        else:
            for i, x in enumerate(members[:-1]):
                checks = [(y, how) for y in members[:i] if (how := relation(q, x, y, symmetry))]
                values = F.filter(f"c{x}", checker(checks)) if checks else F.col(f"c{x}")
                df = df.select(*[c for c in df.columns if c != f"c{x}"], F.explode(values).alias(f"v{x}"))
            last = members[-1]
            checks = [(y, how) for y in members[:-1] if (how := relation(q, last, y, symmetry))]
            total = total * F.size(F.filter(f"c{last}", checker(checks)))
    return df, total


def against(how: str, column: str):
    return lambda e: compare(e, how, F.col(column))


def _below(low: str, high: str) -> Column:
    """Pairs of a value of array low and a larger one of array high: one pass over both, merged by value.

    At equal values those of high come first, so that only strictly smaller ones count.
    """
    zero, one = F.lit(0).cast("bigint"), F.lit(1).cast("bigint")
    tagged = lambda c, tag: F.transform(c, lambda x: F.struct(x.alias("x"), tag.alias("seen")))
    merged = F.array_sort(F.concat(tagged(low, one), tagged(high, zero)))
    step = lambda acc, e: F.struct((acc["seen"] + e["seen"]).alias("seen"), (acc["pairs"] + F.when(e["seen"] == 0, acc["seen"]).otherwise(zero)).alias("pairs"))
    return F.aggregate(merged, F.struct(zero.alias("seen"), zero.alias("pairs")), step, lambda acc: acc["pairs"])


def count(df: DataFrame, q: QueryGraph, symmetry: bool, same: tuple[frozenset[int], ...] = ()) -> DataFrame:
    """One row, column matches: how many plain matches the compressed rows stand for."""
    frame, each = count_column(df, q, symmetry, same)
    return frame.agg(F.coalesce(F.sum(each), F.lit(0)).cast("bigint").alias("matches"))
