"""Box covers: the smallest point of a grid that no box of a group covers.

Boxes are cut down variable by variable: elementary intervals of the first variable, then, within each, of the second.
With any number of variables a cell that one box covers in all variables to come is dropped at once, so the work follows
the boxes that are needed to cover what is not in the result.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from mixagg.model import Factor
from mixagg.sources.steps import kept

Grid = dict[str, tuple[int, int]]  # by variable, in order: its smallest and its largest value
PARTS = 64


def find_gap(boxes: DataFrame, group: str, x: tuple[str, str], y: tuple[str, str], grid_x: tuple[int, int], grid_y: tuple[int, int]) -> DataFrame:
    """group, x, y: the first uncovered grid point, by x then y, of every group that has one (two variables, closed boxes)."""
    cuts = boxes.select(group, F.explode(F.array(F.col(x[0]), F.col(x[1]) + 1, F.lit(grid_x[0]))).alias("at")).where(F.col("at").between(*grid_x)).distinct()
    # within an elementary stretch that starts at a cut, the covering boxes do not change
    over = cuts.join(boxes, group, "left").where((F.col(x[0]) <= F.col("at")) & (F.col("at") <= F.col(x[1]))).select(group, "at", F.col(y[0]).alias("lo"), F.col(y[1]).alias("hi"))
    marks = cuts.select(group, "at", F.lit(grid_y[0] - 1).alias("lo"), F.lit(grid_y[0] - 1).alias("hi")).unionByName(over)
    w = Window.partitionBy(group, "at").orderBy("lo", "hi").rowsBetween(Window.unboundedPreceding, 0)
    reach = marks.withColumn("reach", F.max("hi").over(w))
    nxt = reach.withColumn("next", F.lead("lo").over(Window.partitionBy(group, "at").orderBy("lo", "hi")))
    holes = nxt.where((F.col("reach") + 1 < F.coalesce("next", F.lit(grid_y[1] + 1))) & (F.col("reach") + 1 <= grid_y[1]))
    return holes.groupBy(group).agg(F.min(F.struct(F.col("at").alias("x"), (F.col("reach") + 1).alias("y"))).alias("p")).select(group, F.col("p.x").alias("x"), F.col("p.y").alias("y"))


def _slices(df: DataFrame, low: int, high: int, parts: int) -> tuple[DataFrame, Column, Column]:
    """Equal parts of a variable's values, each with its ends."""
    width = -(-(high - low + 1) // parts)
    part = F.col("part")
    made = df.sparkSession.range(-(-(high - low + 1) // width)).select(F.col("id").alias("part"))
    return made, low + part * width, F.least(low + (part + 1) * width - 1, F.lit(high))


def gap_boxes(f: Factor, grid: Grid, parts: int = PARTS) -> DataFrame:
    """Boxes (lo_v and hi_v by variable) that cover exactly the grid points at which the factor has no row.

    The gaps between neighbouring values of a variable, given those before it in the grid's order; the first variable's
    values are cut into ``parts``, so that no window holds all of them.
    """
    names = [v for v in grid if v in f.vars]
    out = []
    for i, v in enumerate(names):
        before, (low, high) = names[:i], grid[v]
        rows = f.df.where(F.col(v).between(low, high)).select(*before, F.col(v).cast("long").alias("at")).distinct()
        if before:
            by, last = before, F.lit(high)
            first = rows.select(*before).distinct().withColumn("at", F.lit(low - 1).cast("long"))
        else:
            slices, start, last = _slices(f.df, low, high, parts)
            by, first = ["part"], slices.withColumn("at", start - 1)
            rows = rows.withColumn("part", F.floor((F.col("at") - low) / -(-(high - low + 1) // parts)))
        marks = first.unionByName(rows.select(first.columns))
        until = F.coalesce(F.lead("at").over(Window.partitionBy(*by).orderBy("at")) - 1, last)
        gaps = marks.withColumn("until", until).where(F.col("at") + 1 <= F.col("until"))
        ends = lambda u: (F.col("at") + 1, F.col("until")) if u == v else (F.col(u), F.col(u)) if u in before else tuple(map(F.lit, grid[u]))  # noqa: B023, E731
        out.append(gaps.select(*[e.cast("long").alias(f"{side}_{u}") for u in grid for side, e in zip(("lo", "hi"), ends(u))]))
    return reduce(DataFrame.unionByName, out)


def uncovered(boxes: DataFrame, grid: Grid, parts: int = PARTS) -> DataFrame:
    """Disjoint cells (lo_v and hi_v by variable) of exactly the grid points that no box covers.

    The first variable is cut into ``parts`` that are worked on apart; boxes that span several are copied to each.
    """
    names = list(grid)
    low, high = grid[names[0]]
    cells, start, end = _slices(boxes, low, high, parts)
    ends = [f"{side}_{v}" for v in names for side in ("lo", "hi")]
    live = cells.join(boxes.select(*ends), (F.col(f"lo_{names[0]}") <= end) & (F.col(f"hi_{names[0]}") >= start))
    keys, out = ["part"], []
    for i, v in enumerate(names):
        first, last = (start, end) if i == 0 else map(F.lit, grid[v])
        live = kept(live)
        cuts = cells.select(*keys, first.cast("long").alias("at")).unionByName(live.select(*keys, F.explode(F.array(F.greatest(f"lo_{v}", first), F.col(f"hi_{v}") + 1)).alias("at"))).where(F.col("at") <= last).distinct()
        until = F.coalesce(F.lead("at").over(Window.partitionBy(*keys).orderBy("at")) - 1, last)
        stretch = kept(cuts.select(*keys, F.col("at").alias(f"at_{v}"), until.cast("long").alias(f"end_{v}")))
        over = live.join(stretch, keys).where(F.col(f"at_{v}").between(F.col(f"lo_{v}"), F.col(f"hi_{v}")))
        keys = [*keys, f"at_{v}", f"end_{v}"]
        over = kept(over.select(*keys, *ends))
        rest = [F.lit(x).cast("long").alias(f"{side}_{u}") for u in names[i + 1:] for side, x in zip(("lo", "hi"), grid[u])]
        out.append(stretch.join(over.select(*keys).distinct(), keys, "left_anti").select(*[F.col(f"{k}_{u}").alias(f"{side}_{u}") for u in names[: i + 1] for k, side in (("at", "lo"), ("end", "hi"))], *rest))
        if i + 1 == len(names):
            return reduce(DataFrame.unionByName, out)
        whole = reduce(Column.__and__, [(F.col(f"lo_{u}") <= grid[u][0]) & (F.col(f"hi_{u}") >= grid[u][1]) for u in names[i + 1:]])
        live = kept(over.join(over.where(whole).select(*keys).distinct(), keys, "left_anti"))
        cells = live.select(*keys).distinct()


def points(cells: DataFrame, grid: Grid) -> DataFrame:
    for v in grid:
        cells = cells.withColumn(v, F.explode(F.sequence(f"lo_{v}", f"hi_{v}")))
    return cells.select(*grid)


def cover_join(factors: list[Factor], grid: Grid, parts: int = PARTS) -> DataFrame:
    """The join of factors on integer variables as what their gap boxes leave uncovered: variables, v0, v1, ..."""
    out = points(uncovered(reduce(DataFrame.unionByName, [gap_boxes(f, grid, parts) for f in factors]), grid, parts), grid)
    for i, f in enumerate(factors):
        side = f.df.select(*[F.col(v).cast("long").alias(v) for v in f.vars], F.col("val").alias(f"v{i}"))
        out = out.join(side, list(f.vars))
    return out
