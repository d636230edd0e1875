"""Order statistics without moving all rows of a group to one task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .prefixsum import prefix_sum


def ranked(df: DataFrame, by: list[str], order: list[str]) -> DataFrame:
    """df with `rank_` (from 0, in the order within `by`) and `size_` (rows of the group). Ranks come from ranges of the
    whole order, so a group of any size is dealt to many tasks."""
    at = prefix_sum(df, [*by, *order], F.lit(1).cast("bigint"), "at_")
    sizes = at.groupBy(*by).agg(F.min("at_").alias("first_"), F.count("*").alias("size_")) if by else at.agg(F.min("at_").alias("first_"), F.count("*").alias("size_"))
    same = F.lit(True)
    for i, c in enumerate(by):
        sizes = sizes.withColumnRenamed(c, f"by{i}_")
        same &= F.col(c).eqNullSafe(F.col(f"by{i}_"))
    joined = at.join(sizes, same) if by else at.crossJoin(F.broadcast(sizes))  # one row
    return joined.withColumn("rank_", F.col("at_") - F.col("first_")).drop("at_", "first_", *[f"by{i}_" for i in range(len(by))])


def quantiles(df: DataFrame, by: str, value: str, q: dict[str, float]) -> DataFrame:
    """(by, one column for each name of q): exact quantiles, linear between neighbours; nulls are left out."""
    r = ranked(df.filter(F.col(value).isNotNull()).select(by, value), [by], [value])
    ends = []
    for name, share in q.items():
        at = (F.col("size_") - 1) * F.lit(float(share))
        for end, place in (("lo", F.floor(at)), ("hi", F.ceil(at))):
            ends.append(F.max(F.when(F.col("rank_") == place, F.col(value))).alias(f"{end}_{name}_"))
        ends.append(F.max(at - F.floor(at)).alias(f"part_{name}_"))
    g = r.groupBy(by).agg(*ends)
    return g.select(by, *[(F.col(f"lo_{n}_") + (F.col(f"hi_{n}_") - F.col(f"lo_{n}_")) * F.col(f"part_{n}_")).alias(n) for n in q])


def cut_points(df: DataFrame, order: list[str], parts: int) -> DataFrame:
    """One row: `cuts`, the first rows (as structs of `order`) of the second to last of `parts` parts of equal size in the
    order; the first parts have the rows that are left over."""
    r = ranked(df.select(*order), [], order)
    size, more = F.floor(F.col("size_") / parts), F.col("size_") % parts
    firsts = F.array(*[size * k + F.least(F.lit(k), more) for k in range(1, parts)])
    first = F.array_contains(firsts, F.col("rank_")) & (F.col("rank_") > 0)
    return r.filter(first).agg(F.array_sort(F.collect_list(F.struct(*order))).alias("cuts"))
