"""Running values over a long ordered key without one task for the key.

The order is cut into cells of fixed width. Within a cell a window runs over its rows;
over the cells of a key, one summary row each, a second window carries what comes before
(or after) a cell. Both exchanges are by (key, cell), so a node, shard or other hot key is
spread over as many tasks as it has cells.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .columns import div

_ALL = (W.unboundedPreceding, W.unboundedFollowing)


def cell_of(order: str, width: int) -> Column:
    """Number of the cell of an integer position; also right below zero."""
    return F.floor(F.col(order) / F.lit(width)).cast("long") if width == 1 else F.when(F.col(order) >= 0, div(F.col(order), width)).otherwise(-div(-F.col(order) + (width - 1), width))


def running_sums(df: DataFrame, keys: list[str], order: list[str], cell: Column, sums: dict[str, Column]) -> DataFrame:
    """Add for each of `sums` the total of all rows before, by order within keys (0 for the first).

    cell: long, ascending with the order, not null; null sums count as 0; a null key is a key.
    """
    d = df.withColumns({"_cell": cell} | {f"_x_{k}": F.coalesce(v, F.lit(0)).cast("long") for k, v in sums.items()})
    own = W.partitionBy(*keys, "_cell").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    before = W.partitionBy(*keys).orderBy("_cell").rowsBetween(W.unboundedPreceding, -1)
    per = d.groupBy(*keys, "_cell").agg(*(F.sum(f"_x_{k}").alias(f"_s_{k}") for k in sums))
    base = per.select(*keys, "_cell", *(F.coalesce(F.sum(f"_s_{k}").over(before), F.lit(0)).alias(f"_b_{k}") for k in sums))
    inner = d.withColumns({f"_w_{k}": F.coalesce(F.sum(f"_x_{k}").over(own), F.lit(0)) for k in sums})
    base = base.select(*(F.col(k).alias(f"_k_{k}") for k in keys), F.col("_cell").alias("_k_cell"), *(f"_b_{k}" for k in sums))
    same = F.col("_cell") == F.col("_k_cell")
    for k in keys:
        same &= F.col(k).eqNullSafe(F.col(f"_k_{k}"))
    return inner.join(base, same).select(*df.columns, *((F.col(f"_b_{k}") + F.col(f"_w_{k}")).alias(k) for k in sums))


def known_neighbours(df: DataFrame, key: str, order: str, parts: tuple[str, ...], width: int) -> DataFrame:
    """Add <part>_p and <part>_q: struct(order, v) of the last known value at or before, and the first at or after, each row."""
    d = df.withColumn("_cell", cell_of(order, width))
    known = {p: F.when(F.col(p).isNotNull(), F.struct(F.col(order).alias("at"), F.col(p).alias("v"))) for p in parts}
    per = d.groupBy(key, "_cell").agg(*(F.max_by(known[p], F.when(F.col(p).isNotNull(), F.col(order))).alias(f"_l_{p}") for p in parts), *(F.min_by(known[p], F.when(F.col(p).isNotNull(), F.col(order))).alias(f"_f_{p}") for p in parts))
    cells = W.partitionBy(key).orderBy("_cell")
    carried = per.select(
        key, "_cell",
        *(F.last(f"_l_{p}", ignorenulls=True).over(cells.rowsBetween(W.unboundedPreceding, -1)).alias(f"_in_{p}") for p in parts),
        *(F.first(f"_f_{p}", ignorenulls=True).over(cells.rowsBetween(1, W.unboundedFollowing)).alias(f"_out_{p}") for p in parts),
    )
    own = W.partitionBy(key, "_cell").orderBy(order)
    inner = d.withColumns({f"_pw_{p}": F.last(known[p], ignorenulls=True).over(own.rowsBetween(W.unboundedPreceding, 0)) for p in parts} | {f"_qw_{p}": F.first(known[p], ignorenulls=True).over(own.rowsBetween(0, W.unboundedFollowing)) for p in parts})
    j = inner.join(carried, [key, "_cell"])
    return j.select(*df.columns, *(F.coalesce(f"_pw_{p}", f"_in_{p}").alias(f"{p}_p") for p in parts), *(F.coalesce(f"_qw_{p}", f"_out_{p}").alias(f"{p}_q") for p in parts))


def spread(df: DataFrame, first: str, last: str, out: str, width: int) -> DataFrame:
    """A row for each integer in [first, last]: cells first, dealt out anew, then the integers of a cell; no long array."""
    cell = F.explode(F.sequence(cell_of(first, width), cell_of(last, width)))
    cells = df.withColumn("_cell", cell)
    cells = cells.repartition(*df.columns, "_cell")
    a, z = F.greatest(F.col(first), F.col("_cell") * width), F.least(F.col(last), F.col("_cell") * width + (width - 1))
    return cells.withColumn(out, F.explode(F.sequence(a, z))).drop("_cell")


def by_quantiles(df: DataFrame, key: str, order: str, cells: int) -> DataFrame:
    """Add _q, the number of the key's quantiles at or below the row: cells of about even counts.

    One pass gives at most `cells` quantiles a key, by the value types' own order; boundaries
    only cut the work, so that results do not depend on them.
    """
    if cells < 2:
        return df.withColumn("_q", F.lit(0).cast("long"))
    ends = df.groupBy(F.col(key).alias("_of")).agg(F.percentile_approx(order, [(i + 1) / cells for i in range(cells - 1)], 10 * cells).alias("_ends"))
    below = F.size(F.filter(F.coalesce("_ends", F.array()), lambda e: e <= F.col(order)))
    return df.join(ends, F.col(key).eqNullSafe(F.col("_of"))).withColumn("_q", below.cast("long")).drop("_of", "_ends")
