"""Ring and spread cells of medians, draws in cells with portable uniforms, and the new weights."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.expressions import portable_uniform, power_class
from .centres import assign_points

SCALE = 1_000_000

#: Ranges of node ids whose masses are summed before those inside them.
RUNS = 1024


def radius_unit(assigned: DataFrame, alpha: float = 4.0, basis: str = "location_spread") -> DataFrame:
    """One row (radius): estimated expected cost over alpha times the expected weight."""
    expected = F.col("weight") * F.col("mass")
    value = F.col("dist") + F.col("spread") if basis == "location_spread" else F.col("dist")
    return assigned.agg(F.coalesce(F.sum(expected * value) / (F.lit(alpha) * F.sum(expected)), F.lit(0.0)).alias("radius"))


def assign_cells(medians: DataFrame, centres, d: int, alpha: float = 4.0, basis: str = "location_spread") -> DataFrame:
    """Medians with centre, dist, ring and spread_class; ring 0 is an open ball, spread class 0 a closed one."""
    near = assign_points(medians, centres, d)
    with_radius = near.crossJoin(F.broadcast(radius_unit(near, alpha, basis)))
    return with_radius.withColumn("ring", power_class("dist", F.col("radius"), True)).withColumn("spread_class", power_class("spread", F.col("radius"), False))


CELL = ["centre", "ring", "spread_class"]


def cell_stats(cells: DataFrame) -> DataFrame:
    return cells.groupBy(*CELL).agg(F.count("*").alias("n"), F.sum("weight").alias("weight"), F.sum(F.col("weight") * F.col("mass")).alias("expected_weight"), F.sum(F.col("weight") * F.col("mass") * F.col("dist")).alias("cost"))


def max_class(cells: DataFrame) -> DataFrame:
    """One row: the largest ring and spread class and the number of cells that hold nodes."""
    return cells.agg(F.max("ring").alias("max_ring"), F.max("spread_class").alias("max_spread_class"), F.count_distinct(*CELL).alias("n_cells"))


def draw_counts(cells: DataFrame, k: int, per_k: int = 200, allotment: str = "even") -> DataFrame:
    """(cell, n, draws): even shares of the budget over the cells that hold nodes, the literal reading, or by size."""
    sizes = cells.groupBy(*CELL).agg(F.count("*").alias("n"))
    over = sizes.withColumn("cells", F.count("*").over(Window.partitionBy())).withColumn("whole", F.sum("n").over(Window.partitionBy()))
    share = {"even": F.floor(F.lit(per_k * k) / F.col("cells")), "as_printed": F.floor(F.lit(per_k * k) / F.col("n")), "proportional": F.floor(F.lit(per_k * k) * F.col("n") / F.col("whole"))}[allotment]
    return over.select(*CELL, "n", F.greatest(share, F.lit(1)).cast("long").alias("draws"))


def _chance(draw_mass: str) -> Column:
    return {"weight": F.col("weight"), "expected_weight": F.col("weight") * F.col("mass"), "uniform": F.lit(1.0)}[draw_mass]


def draw_cells(cells: DataFrame, k: int, per_k: int = 200, allotment: str = "even", draw_mass: str = "weight", seed: int = 7) -> DataFrame:
    """(cell, node_id, copies, draws): draws with replacement in every cell by integer-scaled running sums.

    A draw's uniform depends on seed, cell and number alone, so any partitioning and any retry draw the same nodes.
    Running sums go over RUNS ranges of the ids first and inside a cell's range then, so a cell of any size is many windows.
    """
    run, place = [*CELL, "run"], Window.unboundedPreceding
    edge = cells.agg(F.min("node_id").alias("_low"), F.max("node_id").alias("_high"))
    width = F.expr("CAST((CAST(_high AS DECIMAL(20)) - _low) / %d AS DECIMAL(20)) + 1" % RUNS)
    rows = cells.crossJoin(F.broadcast(edge)).withColumn("run", F.floor((F.col("node_id").cast("decimal(20)") - F.col("_low")) / width).cast("int"))
    rows = rows.select(*run, "node_id", F.round(_chance(draw_mass) * SCALE).cast("long").alias("m"))
    runs = rows.groupBy(*run).agg(F.sum("m").alias("rm"))
    runs = runs.withColumn("start", F.sum("rm").over(Window.partitionBy(*CELL).orderBy("run").rowsBetween(place, 0)) - F.col("rm"))
    totals = runs.groupBy(*CELL).agg(F.sum("rm").alias("total"))
    upto = F.sum("m").over(Window.partitionBy(*run).orderBy("node_id").rowsBetween(place, 0)) + F.col("start")
    spans = rows.join(runs, run).withColumn("upto", upto).select(*run, "node_id", (F.col("upto") - F.col("m")).alias("low"), "upto")
    name = F.concat_ws("/", *CELL)
    tries = draw_counts(cells, k, per_k, allotment).join(totals, CELL).select(*CELL, "total", "draws", F.explode(F.sequence(F.lit(1), F.col("draws"))).alias("t"))
    tries = tries.withColumn("at", F.floor(portable_uniform(seed, name, F.col("t")) * F.col("total")).cast("long")).select(*CELL, "draws", "t", "at")
    # As-of match without a cross product: draws and spans in one order, each draw takes the run, then the span it stands in.
    none = F.lit(None).cast("long")
    heads = runs.where("rm > 0").select(*CELL, F.col("start").alias("x"), F.lit(0).alias("kind"), "run", none.alias("draws"))
    last = F.last("run", ignorenulls=True).over(Window.partitionBy(*CELL).orderBy("x", "kind").rowsBetween(place, 0))
    placed = heads.unionByName(tries.select(*CELL, F.col("at").alias("x"), F.lit(1).alias("kind"), F.lit(None).cast("int").alias("run"), "draws")).withColumn("run", last).where("kind = 1")
    marks = spans.where("upto > low").select(*run, F.col("low").alias("x"), F.lit(0).alias("kind"), "node_id", none.alias("draws")).unionByName(placed.select(*run, "x", "kind", none.alias("node_id"), "draws"))
    last = F.last("node_id", ignorenulls=True).over(Window.partitionBy(*run).orderBy("x", "kind").rowsBetween(place, 0))
    hits = marks.withColumn("hit", last).where("kind = 1")
    return hits.groupBy(*CELL, F.col("hit").alias("node_id")).agg(F.count("*").alias("copies"), F.max("draws").alias("draws"))


def reweight(cells: DataFrame, drawn: DataFrame, draw_mass: str = "weight") -> DataFrame:
    """Drawn nodes with the inverse-probability weight copies * w / (s * q), q the chance of one draw."""
    chance = _chance(draw_mass)
    totals = cells.groupBy(*CELL).agg(F.sum(chance).alias("whole"))
    kept = cells.join(drawn, [*CELL, "node_id"]).join(totals, CELL)
    return kept.select(*CELL, "node_id", F.col("copies").cast("int").alias("copies"), (F.col("copies") * F.col("weight") * F.col("whole") / (F.col("draws") * chance)).alias("weight"))


def summary_nodes(nodes: DataFrame, weights: DataFrame) -> DataFrame:
    """Packed nodes of the summary: supports stay as they are, weights are the new ones."""
    return nodes.drop("weight").join(weights.select("node_id", "weight", "copies"), "node_id").select("node_id", "weight", "mass", "support", "copies")
