"""Choosing a split policy from a sample of the data and a log of queries."""

from __future__ import annotations

from dataclasses import replace
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid.build import assign_cells
from cubegrid.plans.predicate import make_box
from cubegrid.policy import SplitPolicy


def recommend_policy(df: DataFrame, base: SplitPolicy, boxes: list[tuple], factors: dict[str, list[int]], sample: float = 0.001, lookup_cost: float = 1.0, row_cost: float = 0.02, header_share: float = 0.5, most_cells: int | None = None) -> tuple[SplitPolicy, DataFrame]:
    """Try multiples of the base widths; return the cheapest policy and the table of costs.

    All candidates are evaluated over one sampled pass of the data: coarser coordinates are whole
    divisions of the base coordinates, so the sample is grouped once by base cell.
    ``header_share`` is the share of queries that headers can answer.
    """
    spark = df.sparkSession
    rows = df.sample(sample, seed=7) if sample < 1 else df
    cells = assign_cells(rows, base).groupBy(*base.columns).agg(F.count("*").alias("n")).withColumn("n", F.col("n") / sample)
    cells = cells.cache()
    names = list(factors)
    results = []
    for combo in product(*[factors[n] for n in names]):
        f = dict(zip(names, combo, strict=True))
        policy = SplitPolicy([replace(d, width=d.width * f.get(d.name, 1)) for d in base.dims], base.time_dim)
        coarse = cells.select(*[F.call_function("div", F.col(d.column) - F.pmod(F.col(d.column), F.lit(f.get(d.name, 1))), F.lit(f.get(d.name, 1))).alias(d.column) for d in base.dims], "n")
        merged = coarse.groupBy(*base.columns).agg(F.sum("n").alias("n"))
        outs = [F.count("*").alias("cells")]
        for k, ranges in enumerate(boxes):
            box = make_box(policy, ranges)
            rel, inner = box.related(), box.inner()
            outs += [F.count_if(rel).alias(f"c{k}"), F.coalesce(F.sum(F.when(rel, F.col("n"))), F.lit(0.0)).alias(f"r{k}"), F.coalesce(F.sum(F.when(rel & ~inner, F.col("n"))), F.lit(0.0)).alias(f"b{k}")]
        got = merged.agg(*outs).first()
        cost = sum(got[f"c{k}"] * lookup_cost + row_cost * (header_share * got[f"b{k}"] + (1 - header_share) * got[f"r{k}"]) for k in range(len(boxes)))
        if most_cells is None or got["cells"] <= most_cells:
            results.append((float(cost), int(got["cells"]), [str(f.get(d.name, 1)) for d in base.dims], policy))
    cells.unpersist()
    if not results:
        raise ValueError("no candidate keeps within the number of cells")
    results.sort(key=lambda r: (r[0], r[1]))
    table = spark.createDataFrame([(r[0], r[1], r[2]) for r in results], "cost double, cells long, factors array<string>")
    return results[0][3], table
